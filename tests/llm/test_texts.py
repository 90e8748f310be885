"""Operators on documents: brute force on small tables and the defined odd cases."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from corpus_samples import prose
from pyspark.sql import functions as F

from prunegraph.llm import minhash, mixing, packing, quality, sharding, suffixes, toxicity
from prunegraph.llm.queries import queries, tokenizer_path

FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(text, n):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(FOLD))
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())


def brute_components(texts: dict, n: int, percent: int) -> dict:
    sets = {d: shingles(t, n) for d, t in texts.items()}
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if sets[a] and sets[b]:
                both = len(sets[a] & sets[b])
                if 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                    x, y = find(a), find(b)
                    parent[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), find(d)) for d in ids}


def brute_repeats(texts: dict, length: int = 100) -> dict:
    seen, out = set(), {}
    for d in sorted(texts):
        data = (texts[d] or "").encode()
        gone = bytearray(len(data))
        for i in range(len(data) - length + 1):
            w = data[i : i + length]
            if w in seen:
                gone[i : i + length] = b"\1" * length
            seen.add(w)
        kept = bytes(c for c, g in zip(data, gone) if not g)
        spans = sum(1 for i, g in enumerate(gone) if g and (not i or not gone[i - 1]))
        out[d] = (len(data), sum(gone), spans, hashlib.sha256(kept).hexdigest())
    return out


@pytest.fixture(scope="module")
def docs(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet").persist()


@pytest.fixture(scope="module")
def texts(docs):
    return {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}


# ------------------------------------------------------------------ near duplicates


@pytest.mark.parametrize("words,percent", [(3, 85), (5, 80)])
def test_minhash_equals_brute_force(docs, texts, words, percent):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in minhash.near_duplicates(docs, words, percent).collect()}
    assert got == brute_components(texts, words, percent)


def test_minhash_odd(odd, empty):
    rows = minhash.near_duplicates(odd, 3, 85).collect()
    assert len(rows) == odd.count()
    by = {r["doc_id"]: r for r in rows}
    assert by[1]["n_shingles"] == by[2]["n_shingles"] == by[3]["n_shingles"] == 0 and by[4]["n_shingles"] == 1
    assert by[6]["component_id"] == 5 and not by[6]["kept"] and by[7]["component_id"] == 5
    assert by[1]["kept"] and by[8]["kept"] and by[9]["kept"]
    assert minhash.near_duplicates(empty, 3, 85).count() == 0


def test_minhash_of_one_id_with_several_texts(spark):
    p, q = prose(41, 60), prose(42, 60)
    rows = [(1, p + " end"), (2, q), (2, p), (2, q), (3, q + " end"), (4, prose(43, 60)), (None, p), (5, ""), (5, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("near_key", F.lit(0))
    got = sorted((r["doc_id"] or 0, r["component_id"] or 0) for r in minhash.near_duplicates(df).collect())
    assert got == [(0, 0), (1, 1), (2, 1), (2, 2), (2, 2), (3, 2), (4, 4), (5, 5), (5, 5)]
    left = sorted((r["doc_id"] or 0, r["text"]) for r in minhash.without_near_duplicates(df).collect())
    assert left == sorted([(0, p), (1, p + " end"), (2, q), (4, prose(43, 60)), (5, ""), (5, "")])


def test_minhash_large_group(spark):
    base = prose(1, 120).split()
    rows = []
    for i in range(300):
        w = list(base)
        w[(7 * i) % 120] = f"x{i}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_components(dict(rows), 3, 85)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in minhash.near_duplicates(df, 3, 85).collect()} == want


def test_components_of_known_links(spark, monkeypatch):
    """Later links join known components; small tasks, several levels and the rounds give the same."""
    from prunegraph.llm import common

    rng = np.random.default_rng(3)
    chain = rng.permutation(60) + 1000
    links = [tuple(map(int, x)) for x in [*rng.integers(0, 400, (260, 2)), *zip(chain, chain[1:])]]
    want = {}
    for a, b in links:
        if a != b:
            low, high = sorted((want.setdefault(a, a), want.setdefault(b, b)))
            want.update({k: low for k, v in want.items() if v == high})
    frame = lambda rows: common.materialize(spark.createDataFrame(rows, "a long, b long").repartition(4), "test-links")
    for most, levels, small in ((1 << 20, 3, 1000), (40, 3, 1000), (40, 1, 0), (40, 0, 0)):
        monkeypatch.setattr(common, "SMALL_LABELS", small)
        known = None
        for part in (links[:100], links[100:150], links[100:120], links[150:]):
            known = common.components(frame(part), "test", known, levels, most)
        rows = known.collect()
        assert len(rows) == len(want) and {r["id"]: r["component"] for r in rows} == want
    written = []
    monkeypatch.setattr(common, "SMALL_LABELS", 1000)
    monkeypatch.setattr(common, "materialize", lambda df, name, own=common.materialize: written.append(name) or own(df, name))
    # a link inside a component, and a chain, take one step and no rounds
    assert common.components(frame(links[:1]), "test", known) is known and len(written) == 2
    common.components(frame(list(zip(chain.tolist(), chain[1:].tolist()))), "test")
    assert written[2:] == ["test-links", "test-stars"]


def test_minhash_star_of_copies(spark):
    base = [f"w{i}" for i in range(200)]
    rng = np.random.default_rng(3)
    rows = [(500, " ".join(base))]
    for i in range(1000):
        w = list(base)
        for at in 8 + 10 * rng.choice(19, 4, replace=False):  # copies are alike 0.886 to the original, most of them 0.784 to each other
            w[at] = f"x{i}"
        rows.append((i if i < 500 else i + 1, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in minhash.near_duplicates(df, 3, 85).collect()}
    assert got == {d: 0 for d, _ in rows}


# ------------------------------------------------------------------ repeated passages


def test_repeats_equal_brute_force(docs, texts):
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffixes.remove_repeats(docs).collect()}
    assert got == brute_repeats(texts)


def test_repeats_inside_and_between(spark):
    passage = prose(3, 30)
    rows = [(i, prose(100 + i, 12) + passage + prose(200 + i, 12)) for i in range(40)]
    rows += [(90, "abc" * 200), (91, "x" * 500), (92, passage * 3), (93, passage.upper())]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffixes.remove_repeats(df).collect()}
    assert got == brute_repeats(dict(rows))


def digests(df):
    return {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffixes.remove_repeats(df).collect()}


@pytest.mark.parametrize("shard,gathered,merged", [(2000, 2, 1 << 21), (900, 1, 400), (1 << 21, 3, 1 << 21)])
def test_repeats_in_cut_anchors(spark, monkeypatch, shard, gathered, merged):
    """Anchors spread over many shards, whose windows are merged from sorted packs."""
    monkeypatch.setattr(suffixes, "SHARD_BYTES", shard)
    monkeypatch.setattr(suffixes, "GATHERED", gathered)
    monkeypatch.setattr(suffixes, "MERGED", merged)
    passage = prose(4, 25)
    rows = [(i, prose(300 + i, 10) + passage + prose(400 + i % 7, 10)) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert digests(df) == brute_repeats(dict(rows))


def test_merged_packs():
    rng = np.random.default_rng(0)
    packs, first = [], {}
    for k in range(7):
        value = np.unique(rng.integers(-50, 50, 30))
        doc, start = rng.integers(0, 20, len(value)), np.arange(len(value)) + 100 * k
        packs.append(np.stack([value, value * 3, doc, start]))
        for v, d, s in zip(value.tolist(), doc.tolist(), start.tolist()):
            first.setdefault(v, []).append((d, s))
    pack, late = suffixes.merge_all(packs)
    assert pack[0].tolist() == sorted(first) and list(zip(*pack[2:].tolist())) == [min(first[v]) for v in sorted(first)]
    assert sorted(zip(*late.tolist())) == sorted(x for v in first.values() for x in sorted(v)[1:])
    parts = suffixes._range_of(np.array([-(1 << 63), -1, 0, (1 << 63) - 1]), 4)
    assert parts.tolist() == [0, 1, 2, 3] or parts.tolist() == [0, 2, 2, 3]


def test_repeats_of_one_id_with_several_texts(spark):
    p, q = prose(31, 40), prose(32, 40)
    df = spark.createDataFrame([(1, p), (2, q), (2, p), (2, q), (3, q + p)], "doc_id long, text string")
    rows = sorted((r["doc_id"], r["n_bytes"], r["n_removed"]) for r in suffixes.remove_repeats(df).collect())
    assert rows == sorted([(1, len(p), 0), (2, len(q), 0), (2, len(p), len(p)), (2, len(q), 0), (3, len(p + q), len(p + q))])
    assert sorted(r["text"] for r in suffixes.without_repeats(df.withColumn("runs_doc", F.lit(1))).collect()) == sorted([p, q, "", q, ""])


def test_repeats_odd(odd, empty):
    rows = suffixes.remove_repeats(odd).collect()
    assert len(rows) == odd.count()
    by = {r["doc_id"]: r for r in rows}
    assert by[1]["n_bytes"] == by[2]["n_bytes"] == 0 and by[6]["n_removed"] == by[6]["n_bytes"] and by[10]["n_removed"] > 1800
    assert suffixes.remove_repeats(empty).count() == 0
    cut = suffixes.without_repeats(odd)
    assert cut.columns == odd.columns and cut.count() == odd.count()


def test_suffix_array_and_prefixes():
    rng = np.random.default_rng(0)
    raw = rng.integers(97, 99, 400).astype(np.uint8)
    sa = suffixes.suffix_array(raw, 400)
    data = raw.tobytes()
    assert sa.tolist() == sorted(range(400), key=lambda i: data[i:])
    lcp = suffixes.common_prefixes(raw, sa, np.array([0]), np.array([400]), 100)
    for k in range(1, 400):
        a, b = data[sa[k - 1] :], data[sa[k] :]
        n = 0
        while n < min(len(a), len(b), 100) and a[n] == b[n]:
            n += 1
        assert lcp[k] == n


# ------------------------------------------------------------------ packing


def test_packing_ids_are_those_of_the_whole_text(docs, texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path())
    rows = packing.pack_documents(docs, tokenizer_path()).collect()
    by = defaultdict(list)
    for r in rows:
        by[r["doc_id"]].append(r)
    for d, parts in by.items():
        ids = [*t.encode(texts[d], add_special_tokens=False).ids, 2]
        at = 0
        for p in sorted(parts, key=lambda p: p["start"]):
            piece = np.array(ids[at : at + p["length"]], "<u4").tobytes()
            assert p["start"] == at and p["doc_tokens"] == len(ids) and p["ids_crc32"] == zlib.crc32(piece)
            at += p["length"]
        assert at == len(ids)
    check_sequences(rows)
    total = sum(r["length"] for r in rows)
    assert len({r["sequence_id"] for r in rows}) <= 1.05 * total / 4096 + 2


def check_sequences(rows):
    by = defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 4096


def test_packing_odd(odd, empty):
    rows = packing.pack_documents(odd, tokenizer_path()).collect()
    check_sequences(rows)
    size = Counter()
    for r in rows:
        size[r["doc_id"]] += r["length"]
    assert size[1] == size[2] == size[3] == 1 and size[8] > 20_000
    assert len({r["row_id"] for r in rows if r["doc_id"] == 9}) == 2 and len({r["row_id"] for r in rows}) == odd.count()
    assert packing.pack_documents(empty, tokenizer_path()).count() == 0


@pytest.mark.parametrize("text", ["It's 'quoted' don't stop... a.b,c d'll", "ΑΣ ΟΔΥΣΣΕΥΣ.", "été, İstanbul <|endoftext|> x", "tab\tand nbsp em 12,345.67 !!..,", "a\x1cb\x85c"])
def test_words_equal_whole_encoding(text):
    words = packing.WordTokens(tokenizer_path())
    want = words.tokenizer.encode(text, add_special_tokens=False).ids
    assert np.frombuffer(words.texts([text])[0], "<u4").tolist() == want


def test_packing_words_of_odd_texts_are_those_of_the_whole_text():
    words = packing.WordTokens(tokenizer_path())
    odd = ["J\u030c x J\u030c.", "<|ENDOFTEXT|> a", "<|endoftext|>b", "a\x01b \x01 c", "ﬁ ² Ⅷ. x²,", "\t. a\t. a\x1c.", "foo.bar,, baz...", "_a_. 'S'' 't. it's, can't!''", "ẞ. ǅ, 日本。語、 😀. a😀,"]
    whole = [words.tokenizer.encode(t, add_special_tokens=False).ids for t in odd]
    assert [np.frombuffer(b, "<u4").tolist() for b in words.texts(odd)] == whole


def test_packing_keeps_words_in_use_when_memory_is_full():
    words, encoded = packing.WordTokens(tokenizer_path(), known=40), []
    once = words.encoded
    words.encoded = lambda some: (encoded.extend(some), once(some))[1]
    for i in range(30):
        words.texts([f"common words, stay known. rare{'abcdefghij'[i % 10] * (1 + i)}!"])
    assert encoded.count("common") == 1 and encoded.count(".") == 1
    assert len(words.ids) + len(words.older) <= 40 + 2 * 12


def test_histogram_packing_is_tight():
    rng = np.random.default_rng(1)
    lengths = np.unique(rng.integers(1, 4097, 500))
    counts = rng.integers(1, 300, len(lengths))
    runs = packing.pack_histogram(lengths, counts)
    used = Counter()
    for offset, length, n, pack in sorted(zip(*(runs[c].tolist() for c in ("offset", "length", "count", "pack")))):
        for k in range(n):
            assert used[pack + k] == offset
            used[pack + k] += length
    assert max(used.values()) <= 4096 and sum(runs["count"]) == counts.sum()
    assert len(used) * 4096 < 1.1 * (lengths * counts).sum() + 4096


# ------------------------------------------------------------------ sharding


def test_sharding(spark, docs, small, tmp_path):
    rows = queries()["op4_sharding"](spark, small).collect()
    load, slots = Counter(), defaultdict(list)
    for r in rows:
        load[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
    assert set(load) <= set(range(40)) and all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert max(load.values()) <= sum(load.values()) / 40 + max(r["size"] for r in rows)
    by = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    assert all(r["size"] == len(by[r["doc_id"]].encode()) + 16 and r["text_crc32"] == zlib.crc32(by[r["doc_id"]].encode()) for r in rows)
    placed, first = sharding.shard(docs, 8)
    again = sharding.rebalance(sharding.slot_bytes(sharding.records(docs)), 9, first, version=2)
    sharding.save_map(first, f"{tmp_path}/map")
    sharding.save_map(again, f"{tmp_path}/map")
    old = {r["vslot"]: r["shard"] for r in sharding.load_map(spark, f"{tmp_path}/map", 1).collect()}
    new = {r["vslot"]: (r["shard"], r["bytes"]) for r in sharding.load_map(spark, f"{tmp_path}/map", 2).collect()}
    moved = sum(b for s, (k, b) in new.items() if old[s] != k)
    assert len(new) == sharding.SLOTS and moved < 0.35 * sum(b for _, b in new.values())


def test_slot_map_equals_greedy_fold(docs):
    """The map against the rule written out: largest slot first, to the emptiest shard or where it was."""
    stats = sharding.slot_bytes(sharding.records(docs)).persist()
    first = sharding.rebalance(stats, 7).persist()
    second = sharding.rebalance(stats, 8, first, version=2)
    sizes = [(r["vslot"], r["bytes"]) for r in stats.collect()]
    was: dict = {}
    for shards, slot_map in ((7, first), (8, second)):
        load, share, to = [0] * shards, sum(b for _, b in sizes) / shards, {}
        for b, v in sorted(((b, v) for v, b in sizes), reverse=True):
            k = was.get(v, -1)
            if not (0 <= k < shards and load[k] + b <= share):
                k = load.index(min(load))
            load[k] += b
            to[v] = k
        assert {r["vslot"]: r["shard"] for r in slot_map.collect()} == to
        was = to


def test_sharding_spreads_copies_of_one_row(spark):
    rows = [(7, "copy " * 40)] * 3000 + [(i, prose(i, 20)) for i in range(8, 3000)]
    placed, _ = sharding.shard(spark.createDataFrame(rows, "doc_id long, text string").withColumn("copy", F.lit(9)))
    load, most = Counter(), Counter()
    for r in placed.collect():
        load[r["shard"]] += r["size"]
        most[r["vslot"]] += r["doc_id"] == 7
    assert max(most.values()) < 20 and max(load.values()) < 1.05 * sum(load.values()) / 40


def test_sharding_odd(odd, empty):
    placed, _ = sharding.shard(odd)
    assert placed.count() == odd.count() and placed.filter("doc_id = 1").first()["size"] == 16
    assert sharding.shard(empty)[0].count() == 0


# ------------------------------------------------------------------ toxicity and quality


def test_toxicity_finds_planted_words(spark):
    rows = [(i, prose(i, 80) + (" you idiot moron" if i % 5 == 0 else "")) for i in range(600)]
    labels = spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(600)], "doc_id long, toxic int")
    df = spark.createDataFrame(rows, "doc_id long, text string")
    found = toxicity.classify(df, labels).collect()
    held = [r for r in found if r["held_out"]]
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in found)
    assert np.mean([r["predicted"] == (r["doc_id"] % 5 == 0) for r in held]) > 0.97


def test_toxicity_equals_brute_force(spark):
    """Selected n-grams, their ratios and the scores against dictionaries of strings."""
    texts = [prose(i, 30) + (" you idiot moron" if i % 4 == 0 else "") for i in range(120)]
    y = [int(i % 4 == 0) for i in range(120)]
    model = toxicity.fit(spark.createDataFrame(list(zip(texts, y)), "text string, toxic int"))
    grams = [{t[i : i + n] for n in toxicity.ORDERS for i in range(len(t) - n + 1)} for t in map(str.lower, texts)]
    bad, good = Counter(), Counter()
    for g, v in zip(grams, y):
        (bad if v else good).update(g)
    n_bad, n_good = sum(y), len(y) - sum(y)
    ratio = {}
    for g in {*bad, *good}:
        p, q = bad[g] + 0.5, good[g] + 0.5
        r = np.log(p / (n_bad + 1)) - np.log(q / (n_good + 1))
        if bad[g] + good[g] >= 3 and abs(r) / np.sqrt(1 / p + 1 / q) >= toxicity.LEAST_Z:
            ratio[g] = r

    def name(g):
        return {n: h for n, h in toxicity._grams([g])[2]}[len(g)][0]

    key = {int(name(g)): g for g in ratio}
    assert sorted(key) == model.keys.tolist()
    weight = {key[int(k)]: w for k, w in zip(model.keys, model.weights)}
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in toxicity.score(df, model).collect():
        z = model.intercept + sum(weight.get(g, 0.0) for g in grams[r["doc_id"]])
        assert r["score"] == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-9)


def test_toxicity_odd(spark, odd, empty):
    labels = spark.createDataFrame([(5, 0), (8, 1), (4, 1), (2, 0), (None, 1), (6, None)], "doc_id long, toxic int")
    rows = toxicity.classify(odd, labels).collect()
    assert len(rows) == odd.count() and all(0 <= r["score"] <= 1 for r in rows)
    assert [r["held_out"] for r in rows if r["doc_id"] is None] == [False]
    assert toxicity.classify(empty, labels).count() == 0
    none = spark.createDataFrame([], "doc_id long, toxic int")
    assert all(r["score"] < 0.01 for r in toxicity.classify(odd, none).collect())


def kneser_ney(texts, order):
    """The model written out over dictionaries."""
    pad = "\x01"
    level = {order: Counter()}
    for t in texts:
        s = pad * (order - 1) + t + pad
        level[order].update(s[i : i + order] for i in range(len(s) - order + 1))
    for k in range(order - 1, 0, -1):
        level[k] = Counter(g[1:] for g in level[k + 1])
    d = {k: quality.discounts(Counter(v for v in c.values() if v <= 4)) for k, c in level.items()}
    off = lambda k, c: d[k][min(c, 3) - 1]
    total, freed = defaultdict(Counter), defaultdict(Counter)
    for k, c in level.items():
        for g, n in c.items():
            total[k][g[:-1]] += n
            freed[k][g[:-1]] += off(k, n)

    def p(g):
        k = len(g)
        lower = p(g[1:]) if k > 1 else 1 / 256
        ctx = g[:-1]
        if not total[k][ctx]:
            return lower
        n = level[k][g]
        return ((n - off(k, n)) if n else 0) / total[k][ctx] + freed[k][ctx] / total[k][ctx] * lower

    return lambda t: sum(np.log(p((pad * (order - 1) + t + pad)[i : i + order])) for i in range(len(t) + 1))


def test_quality_model_equals_dictionaries(spark):
    fit = [prose(i, 40) for i in range(20)]
    other = [prose(99, 30), "zzz %% zzz", "", "alpha"]
    model = kneser_ney(fit, 4)
    df = spark.createDataFrame([(i, t, True) for i, t in enumerate(fit)] + [(100 + i, t, None) for i, t in enumerate(other)], "key long, text string, fit boolean")
    prob = quality.probabilities(quality.string_counts(df, 4), 4)
    for head in (1 << 19, 50):
        got = {r["key"]: r["log_likelihood"] for r in quality.scores(df, prob, 4, head).collect()}
        for i, t in enumerate(other):
            assert got[100 + i] == pytest.approx(model(t), rel=1e-4, abs=1e-4)


def test_quality_scores_repeated_rows_each(spark):
    text = prose(99, 30)
    rows = [(i, prose(i, 40), True) for i in range(20)] + [(100, text, None)] + [(101, text, None)] * 5
    df = spark.createDataFrame(rows, "key long, text string, fit boolean")
    prob = quality.probabilities(quality.string_counts(df, 4), 4)
    got = [(r["key"], r["log_likelihood"]) for r in quality.scores(df, prob, 4, 50).collect() if r["key"] >= 100]
    once = dict(got)[100]
    assert len(got) == 6 and all(x == pytest.approx(once, rel=1e-6) for _, x in got)


def test_quality_keeps_clean_and_drops_junk(spark):
    rows = [(i, prose(i, 60), "en", "a", 0) for i in range(400)] + [(400 + i, "".join(f"@{(i * 7 + k) % 10}^~" for k in range(80)), "en", "a", 0) for i in range(20)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([(i, 1) for i in range(0, 400, 2)], "doc_id long, quality int")
    kept = {r["doc_id"] for r in quality.select_quality(df, labels).collect()}
    assert not kept & set(range(400, 420)) and len(kept) >= 396


def test_quality_odd(spark, odd, empty):
    labels = spark.createDataFrame([(5, 1), (8, 1), (4, 0), (None, 1), (6, None)], "doc_id long, quality int")
    found = quality.score_quality(odd, labels).collect()
    assert len(found) == odd.count() and all(r["kept"] == (r["n_bytes"] == 0 or r["smoothed_perplexity"] <= r["threshold"]) for r in found)
    assert quality.select_quality(odd, labels).columns == odd.columns
    assert quality.score_quality(empty, labels).count() == 0
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert quality.select_quality(odd, none).count() == odd.count()


# ------------------------------------------------------------------ mixing


def test_mixing_equals_brute_force(spark):
    """Every realised row against the rule written out over lists."""
    rows = [(i, prose(i, 5 + i % 40), "abc"[0 if i < 150 else 1 + i % 2]) for i in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mix(df, most_repeats=2.5, block_tokens=300).collect()
    size = {d: max(1, -(-len(t.encode()) // 4)) for d, t, _ in rows}
    total = Counter()
    for d, _, s in rows:
        total[s] += size[d]
    names = sorted(total)
    budget = sum(total.values())
    w = dict(zip(names, mixing.weights([total[s] for s in names], mixing.bisect_exponent([total[s] for s in names], budget, 2.5))))
    by = defaultdict(list)
    for r in got:
        by[r["source"], r["epoch"]].append(r)
    for s in names:
        quota = round(w[s] * budget)
        epochs, rest = divmod(quota, total[s])
        mine = {d for d, _, x in rows if x == s}
        block_of = {r["doc_id"]: r["block"] for r in got if r["source"] == s}
        for e in range(epochs):
            assert {r["doc_id"] for r in by[s, e]} == mine and len(by[s, e]) == len(mine)
        part = sorted(by[s, epochs], key=lambda r: (r["block_rank"], r["place"]))
        held = sum(r["n_tokens"] for r in part)
        assert not rest and not part or held >= rest > held - part[-1]["n_tokens"]
        for e in range(epochs + 1):
            ranks = {}
            for r in by[s, e]:
                assert block_of[r["doc_id"]] == r["block"] and ranks.setdefault(r["block"], r["block_rank"]) == r["block_rank"]
            assert sorted(ranks.values()) == list(range(1, len(ranks) + 1))


def test_mixing_of_many_sources_by_aggregation(spark, monkeypatch):
    rows = [(i, "x" * (4 + 4 * (i % 9)), f"s{i % 23}") for i in range(230)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    few = sorted(tuple(r) for r in mixing.mix(df, target_entropy=3.1).collect())
    monkeypatch.setattr(mixing, "FEW_SOURCES", 5)
    assert sorted(tuple(r) for r in mixing.mix(df, target_entropy=3.1).collect()) == few


def test_mixing_of_repeated_rows(spark):
    """A third of all rows is one row: it is spread over blocks and keeps its number."""
    rows = [(1, "same text", "a")] * 300 + [(i, prose(i, 10), "ab"[i % 2]) for i in range(2, 600)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    picked = mixing.mix(df, budget=None, most_repeats=1.0, block_tokens=100).collect()
    same = [r for r in picked if r["doc_id"] == 1]
    assert len(same) == 300 and len({r["block"] for r in same}) > 5
    out = mixing.mixed_documents(df.withColumn("mix_row", F.lit(1)), most_repeats=1.0)
    assert out.filter("doc_id = 1").count() == 300 and out.count() == len(picked) and out.columns[-1] == "mix_row"


def test_exponent():
    tokens = [900.0, 50.0, 50.0]
    a = mixing.bisect_exponent(tokens, 1000, most_repeats=2.0)
    w = mixing.weights(tokens, a)
    assert max(x * 1000 / t for x, t in zip(w, tokens)) == pytest.approx(2.0, rel=1e-6)
    b = mixing.bisect_exponent(tokens, 1000, target_entropy=0.8)
    assert mixing.entropy(mixing.weights(tokens, b)) == pytest.approx(0.8, rel=1e-6)
    assert mixing.bisect_exponent(tokens, 1000, most_repeats=100) == 0.0


def test_mixing_meets_budgets(docs):
    rows = mixing.mix(docs, most_repeats=1.3, block_tokens=2000).collect()
    tokens = {r["doc_id"]: r["n_tokens"] for r in rows}
    source = {r["doc_id"]: r["source"] for r in docs.collect()}
    size = {r["doc_id"]: max(1, -(-len((r["text"] or "").encode()) // 4)) for r in docs.collect()}
    total = Counter()
    for d, n in size.items():
        total[source[d]] += n
    names = sorted(total)
    w = mixing.weights([total[s] for s in names], mixing.bisect_exponent([total[s] for s in names], sum(total.values()), 1.3))
    got = Counter()
    for r in rows:
        got[r["source"]] += r["n_tokens"]
    longest = max(size.values())
    for s, x in zip(names, w):
        assert abs(got[s] - x * sum(total.values())) <= longest + 1
    times = Counter((r["doc_id"], r["epoch"]) for r in rows)
    assert max(times.values()) == 1 and all(tokens[d] == size[d] for d in tokens)


def test_mixing_odd(odd, empty):
    assert mixing.mix(odd).count() > 0
    out = mixing.mixed_documents(odd)
    assert out.columns == odd.columns
    assert mixing.mix(empty).count() == 0 and mixing.mixed_documents(empty).count() == 0


def test_quality_counts_hold_few_strings():
    """Partial counts add up, and no more strings are held than asked, whatever an Arrow batch holds."""
    import numpy as np
    import pyarrow as pa

    from prunegraph.llm import quality

    rng = np.random.default_rng(3)
    texts = ["".join(chr(97 + c) for c in rng.integers(0, 26, 3000)) for _ in range(700)]
    batch = pa.RecordBatch.from_arrays([pa.array(texts), pa.array([i % 3 == 0 for i in range(700)])], ["text", "fit"])
    parts = list(quality.counted(iter([batch]), 5, 200_000))
    whole = list(quality.counted(iter([batch]), 5, 1 << 30))
    assert len(whole) == 1 and len(parts) > 1 and max(p.num_rows for p in parts) <= 200_000 + quality._BLOCK
    total = lambda found: pa.Table.from_batches(found).group_by("gram").aggregate([("n", "sum"), ("t", "sum")]).sort_by("gram")
    assert total(parts).equals(total(whole))


def test_quality_workers_give_memory_back():
    """Partial counts leave in batches of a bounded size, and no table outlives its task."""
    rng = np.random.default_rng(5)
    texts = ["".join(map(chr, rng.integers(33, 127, 2000))) for _ in range(60)]
    batch = pa.RecordBatch.from_arrays([pa.array(texts), pa.array([i % 2 == 0 for i in range(60)])], ["text", "fit"])
    quality._tables.update(of=None, table=quality.StringTable(np.arange(9, dtype=np.uint64), np.zeros(9, np.float32)))
    out = list(quality.tidied(quality.counted(iter([batch]), 5, 1 << 20)))
    assert len(out) > 1 and max(b.num_rows for b in out) <= 1 << 16
    assert sum(b.column(1).to_numpy().sum() for b in out) == 60 * 2001 == 2 * sum(b.column(2).to_numpy().sum() for b in out)
    assert quality._tables == {}


def test_workers_of_repeats_and_near_duplicates_give_memory_back(spark):
    """What long texts make a worker keep is gone once its task has ended."""
    df = spark.createDataFrame([(i, prose(i, 70_000)) for i in range(2)], "doc_id long, text string").repartition(2)

    def kept(batches):
        from prunegraph.llm import shingles

        list(batches)
        yield pa.RecordBatch.from_arrays([pa.array([len(shingles._power["up"])])], ["n"])

    for run in (minhash.without_near_duplicates, suffixes.without_repeats):
        run(df).count()
        assert run(df).agg(F.sum(F.length("text"))).first()[0] > 500_000
        assert spark.range(64).repartition(16).mapInArrow(kept, "n long").agg(F.max("n")).first()[0] <= 1 << 17
