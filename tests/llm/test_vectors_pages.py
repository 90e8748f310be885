import numpy as np
import pytest
from pyspark.sql import functions as F

from prunegraph.llm import graphs, htmltext, nearest


@pytest.fixture(scope="module")
def vectors(spark):
    rng = np.random.default_rng(0)
    base = rng.standard_normal((60, 16))
    x = np.concatenate([base, base[:20] + 0.05 * rng.standard_normal((20, 16)), np.repeat(base[:1], 30, 0), rng.standard_normal((200, 16))]).astype(np.float32)
    rows = [(i, [float(v) for v in r], int(i % 3)) for i, r in enumerate(x)]
    rows += [(1000, None, 0), (1001, [0.0] * 16, 0), (1002, [float("nan")] * 16, 1), (1003, [1.0, None] + [0.0] * 14, 1), (1004, rows[0][1], None), (1005, [1.0, 2.0], 0), (1006, [], 0)]
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").withColumn("vector", F.lit("clash")).withColumn("rep", F.lit(1)), x


def test_search_recall_and_scores(vectors):
    df, x = vectors
    rows = nearest.search(df, F.col("vec_id") % 5 == 0).collect()
    unit = x.astype(float)
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    ids = [*range(len(x)), 1004]
    full = np.concatenate([unit, unit[:1]])
    hit = total = 0
    for q in range(0, len(x), 5):
        s = full @ unit[q]
        s[q] = -2
        best = [ids[k] for k in np.lexsort((ids, -np.round(s, 12)))[:5]]
        got = [(r["vec_id"], r["score"]) for r in sorted((r for r in rows if r["query_id"] == q), key=lambda r: r["rank"])]
        assert len(got) == 5 and all(abs(v - s[ids.index(i)]) < 1e-12 for i, v in got)
        hit += len(set(best) & {i for i, _ in got})
        total += 5
    assert hit / total >= 0.9
    short = [r for r in rows if r["query_id"] == 1005]
    assert not short and not [r for r in rows if r["query_id"] in (1000, 1001, 1002, 1003)]


def test_search_of_few(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [-1.0, 0.0])], "vec_id long, embedding array<float>")
    rows = nearest.search(df, F.col("vec_id") == 0).orderBy("rank").collect()
    assert [(r["vec_id"], r["score"]) for r in rows] == [(1, 0.0), (2, -1.0)]
    assert nearest.search(df.limit(0), F.col("vec_id") == 0).count() == 0


def test_search_prunes(spark):
    """On vectors with neighbours, a query meets a small part of the table and loses little."""
    rng = np.random.default_rng(5)
    centre = rng.standard_normal((150, 32))
    x = np.repeat(centre, 20, 0) + 0.4 * rng.standard_normal((3000, 32))
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<float>")
    report = {}
    rows = nearest.search(df, F.col("vec_id") % 25 == 0, report=report).collect()
    assert report["recall"] >= 0.9 and report["met"] < 0.35
    unit = x.astype(np.float32).astype(float)
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    hit = 0
    for q in range(0, 3000, 25):
        s = unit @ unit[q]
        s[q] = -2
        hit += len(set(np.argsort(-s)[:5].tolist()) & {r["vec_id"] for r in rows if r["query_id"] == q})
    assert len(rows) == 600 and hit / 600 >= 0.9


def test_search_ties_and_repeated_ids(spark):
    """Multiples of one vector tie; the smaller ids win, also beyond what one block keeps."""
    rng = np.random.default_rng(6)
    v = rng.standard_normal(8)
    rows = [(i, [float(c) for c in v * 2.0 ** (i % 16)]) for i in range(40, 0, -1)]
    rows += [(100 + i % 3, [float(c) for c in v * 3]) for i in range(18)] + [(200 + i, [float(c) for c in rng.standard_normal(8)]) for i in range(50)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [r["vec_id"] for r in nearest.search(df, F.col("vec_id") == 200 - 190).orderBy("rank").collect()]
    assert got == [1, 2, 3, 4, 5]


def test_search_falls_back_to_comparison(spark):
    """Where hashing finds too little, all rows are compared."""
    rng = np.random.default_rng(7)
    df = spark.createDataFrame([(i, [float(c) for c in rng.standard_normal(24)]) for i in range(400)], "vec_id long, embedding array<float>")
    report = {}
    rows = nearest.search(df, F.col("vec_id") % 20 == 0, tables=1, target=0.01, report=report).collect()
    assert len(rows) == 100 and (report["recall"] >= nearest.RECALL or report["tables"] >= nearest.MOST_TABLES)


def test_graph_links_equal_brute_force(vectors):
    df, x = vectors
    unit = x.astype(float)
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    n = len(x)
    label = np.arange(n) % 3
    linked = (unit @ unit.T >= 0.93) & (label[:, None] == label[None])
    np.fill_diagonal(linked, False)
    comp = np.arange(n)
    for _ in range(n):
        comp = np.minimum(comp, np.where(linked, comp[None], n).min(axis=1))
    rows = {r["vec_id"]: r for r in graphs.near_vectors(df).collect()}
    assert len(rows) == n + 7
    for i in range(n):
        assert (rows[i]["n_links"], rows[i]["component_id"], rows[i]["kept"]) == (linked[i].sum(), comp[i], comp[i] == i)
    assert all(rows[i]["n_links"] == 0 and rows[i]["kept"] for i in range(1000, 1007))


def test_graph_over_shards(vectors):
    df, _ = vectors
    a = {tuple(r) for r in graphs.near_vectors(df).collect()}
    b = {tuple(r) for r in graphs.near_vectors(df, shard=40).collect()}
    assert a == b
    assert graphs.near_vectors(df.limit(0)).count() == 0


def test_graph_of_one_cluster_over_shards(spark):
    """A cluster larger than a beam and a shard: all links counted, no row per link."""
    rng = np.random.default_rng(4)
    x = rng.standard_normal(12)[None] + 0.18 * rng.standard_normal((700, 12))
    df = spark.createDataFrame([(i, [float(v) for v in r], 1) for i, r in enumerate(x)], "vec_id long, embedding array<double>, label int")
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    linked = unit @ unit.T >= 0.93
    np.fill_diagonal(linked, False)
    want = linked.sum(axis=1)
    got = {r["vec_id"]: r["n_links"] for r in graphs.near_vectors(df, shard=200).collect()}
    found = np.array([got[i] for i in range(700)])
    assert want.sum() > 20_000 and (found <= want).all() and found.sum() >= 0.999 * want.sum()


def test_forest_joins_what_links_join():
    rng = np.random.default_rng(2)
    linked = np.zeros((60, 50), bool)
    for k in range(4):
        linked[15 * k : 15 * k + 12, 12 * k : 12 * k + 10] = rng.random((12, 10)) < 0.9
    x, y = graphs.forest(linked)
    assert linked[x, y].all() and len(x) < linked.sum()

    def joined(pairs):
        parent = list(range(110))

        def find(v):
            while parent[v] != v:
                v = parent[v]
            return v

        for a, b in pairs:
            p, q = find(a), find(60 + b)
            parent[max(p, q)] = min(p, q)
        return [find(v) for v in range(110)]

    assert joined(zip(x, y)) == joined(zip(*np.nonzero(linked)))


def test_audit_without_links_widens_the_beam():
    x = np.random.default_rng(1).standard_normal((300, 40))
    graph = graphs.SmallWorld(x / np.linalg.norm(x, axis=1, keepdims=True))
    assert graphs.audited(graph, 0.93) >= 2 * graphs.BEAM


PAGE = """<html><head><title>t</title><style>p{}</style></head><body><nav><a href="/x">menu</a></nav><div class="cookie-notice">Accept</div>
<article><h1>Title %d &amp; more</h1><p>First   para<br>graph %d with <b>bold</b> &lt;text&gt;.<p>Second %d<ul><li>one<li>two</ul><aside>side</aside><div class="share">Share</div></article>
<div class="comments"><p>Nice!</p></div><form><p>Mail</p></form><footer>&copy; site</footer><script>var x = "</p><p>no";</script></body></html>"""


def test_pages(spark):
    rows = [(i, "http://a.example/x", PAGE % (i, i, i)) for i in range(6)]
    rows += [(10, None, None), (11, "odd url", ""), (12, "http://b.example/", "<p>only<p>text &eacute;&#233; <div"), (13, "http://c.example/", "<html><body><main><p>x</p></main></body></html>")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit(1)).withColumn("main", F.lit("z"))
    got = {r["page_id"]: r for r in htmltext.extract(df).collect()}
    for i in range(6):
        assert got[i]["text"] == f"Title {i} & more\n\nFirst para graph {i} with bold <text>.\n\nSecond {i}\n\none\n\ntwo"
        assert got[i]["n_chars"] == len(got[i]["text"])
    assert got[10]["text"] == got[11]["text"] == "" and got[10]["n_chars"] == 0
    assert got[12]["text"] == "only\n\ntext éé" and got[13]["text"] == "x"
    assert htmltext.extract(df.limit(0)).count() == 0


def test_pages_without_elements_of_a_name(spark):
    """With article, nav and footer made nameless, classes of template tokens find the text."""
    import re
    from collections import Counter

    df = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    want = {r["page_id"]: r["text"] for r in htmltext.extract(df).collect()}
    pages = df.collect()
    hosts = Counter(r["url"].split("/")[2] for r in pages)
    pages = [r for r in pages if hosts[r["url"].split("/")[2]] >= 5]
    plain = []
    for r in pages:
        html = re.sub(r"</(article|nav|footer)>", "</div>", r["html"])
        for name, other in (("article", "z1"), ("nav", "z2"), ("footer", "z3")):
            html = html.replace(f"<{name}>", f'<div class="{other}">')
        plain.append((r["page_id"], r["url"], html))
    got = {r["page_id"]: r["text"] for r in htmltext.extract(spark.createDataFrame(plain, "page_id long, url string, html string")).collect()}
    assert len(plain) > 100 and sum(got[k] == want[k] for k in got) >= 0.95 * len(plain), sum(got[k] == want[k] for k in got) / len(plain)


def test_pages_with_an_unchanging_slot(spark):
    page = "<html><body><div class='top'><a href='/'>Home</a></div><div class='story'><div class='hint'>Read our terms</div><h1>Title {0}</h1><p>Text number {0} goes on for a while.</p></div></body></html>"
    rows = [(i, "http://d.example/p", page.format(i)) for i in range(8)]
    got = {r["page_id"]: r["text"] for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(got[i] == f"Title {i}\n\nText number {i} goes on for a while." for i in range(8))
    copies = [(i, "http://e.example/p", page.format(1)) for i in range(8)]
    got = [r["text"] for r in htmltext.extract(spark.createDataFrame(copies, "page_id long, url string, html string")).collect()]
    assert all("Text number 1" in t for t in got)


def test_pages_of_the_given_table(spark, small):
    import html
    import re

    df = spark.read.parquet(f"{small}/pages.parquet")
    got = {r["page_id"]: r["text"] for r in htmltext.extract(df).collect()}
    for r in df.collect():
        article = r["html"].split("<article>")[1].split("</article>")[0]
        blocks = [" ".join(html.unescape(re.sub(r"<[^>]+>", " ", b)).split()) for b in re.split(r"</?(?:p|h1)>", article)]
        assert got[r["page_id"]] == "\n\n".join(b for b in blocks if b)
