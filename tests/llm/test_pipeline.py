"""The corpus stages on a small table: what stays, what goes, and the columns."""

from corpus_samples import DOCS, prose

import corpus_pipeline


def test_stages(spark, tmp_path):
    clean = [(i, prose(1000 + i, 60), "en", "a" if i % 3 else "b", 0) for i in range(150)]
    copies = [(200 + i, prose(1000, 60), "en", "a", 0) for i in range(5)]
    near = [(210, prose(1001, 60) + " tail", "en", "a", 0)]
    junk = [(220 + i, "".join(f"@{(i * 7 + k) % 10}^~" for k in range(90)), "en", "a", 0) for i in range(5)]
    shared = [(230, prose(5000, 40) + " " + prose(1002, 60), "en", "b", 0)]
    odd = [(240, None, None, None, None), (241, "", "en", "a", 0)]
    spark.createDataFrame(clean + copies + near + junk + shared + odd, DOCS).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(0, 150, 2)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs, seen = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    names = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.materialize(stage(spark, docs, str(tmp_path)), f"test-{name}")
        seen[name] = docs
        if name != "packing":
            assert docs.columns == names
    ids = {n: {r["doc_id"] for r in d.select("doc_id").collect()} for n, d in seen.items()}
    assert not ids["quality"] & set(range(220, 225)) and len(ids["quality"] & set(range(150))) >= 148
    assert 0 in ids["near_dedup"] and not ids["near_dedup"] & {200, 201, 202, 203, 204, 210}
    text = {r["doc_id"]: r["text"] for r in seen["repeats"].collect()}
    assert prose(1002, 60)[20:-20] not in text[230] and text[2] == prose(1002, 60)
    pieces = seen["packing"].collect()
    assert sum(r["length"] for r in pieces) == sum(r["doc_tokens"] for r in pieces if r["start"] == 0)
