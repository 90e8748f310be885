"""Statistics, selectors, cost and accuracy measures, baselines."""

from __future__ import annotations

import datetime as dt

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.functions import attributes as A
from prunegraph.functions import cost as C
from prunegraph.functions import metrics as M
from prunegraph.operators import baselines as B
from prunegraph.operators import edges as E
from prunegraph.operators import prune as P
from prunegraph.operators import store as S
from prunegraph.operators.layers import AttentionLayer, formula_weights, infer_full
from prunegraph.operators.propagate import propagate_k
from prunegraph.operators.support import make_batches, support_sets
from prunegraph.plans.headline import HIDDEN, WIDTH, base, cells, fixed_column, given_mask, targets_of, two_layer
from prunegraph.plans.sqltext import NODES, SPLIT, Plan, fixed
from prunegraph.sources.tables import node_ids, read

ETAS = {"1x": 1.0, "2x": 0.5, "4x": 0.25, "8x": 0.125}


def _train(nodes):
    return nodes.filter(E.split_of() == "train")


def _grams(spark, folder):
    nodes, edges, feats = base(spark, folder)
    return P.branch_grams(edges, feats, _train(nodes), WIDTH, [0, 1])


def _matrix(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def gram_branch(spark, folder):
    g = _grams(spark, folder)[1]
    return _matrix(spark, [(j, l, int(np.floor(g[j, l] * 1e6 + 0.4999))) for j in range(WIDTH) for l in range(WIDTH)], "j int, l int, v long")


def lasso_terms(spark, folder):
    g = _grams(spark, folder)
    q, r = P.mask_terms(g, {k: formula_weights(1, k, WIDTH, HIDDEN) for k in (0, 1)})
    rows = [("q", j, l, int(np.floor(q[j, l] * 1e4 + 0.4999))) for j in range(WIDTH) for l in range(WIDTH)]
    rows += [("r", j, 0, int(np.floor(r[j] * 1e4 + 0.4999))) for j in range(WIDTH)]
    return _matrix(spark, rows, "term string, j int, l int, v long")


def lasso_mask_path(spark, folder):
    """Masks along a rising penalty, in hundredths of the largest useful one."""
    q, r = P.mask_terms(_grams(spark, folder), {k: formula_weights(1, k, WIDTH, HIDDEN) for k in (0, 1)})
    beta, rows = None, []
    for step in (0, 1, 2, 5, 10, 20, 50, 100):
        beta = P.lasso_mask(q, r, step / 100 * 2 * np.abs(r).max(), beta, sweeps=20000, tol=1e-12)
        rows += [(step, j, int(np.floor(beta[j] * 1e6 + 0.4999))) for j in range(WIDTH)]
    return _matrix(spark, rows, "penalty int, ch int, v long")


def _channel_sums(spark, folder, *by):
    """Sum in millionths of every channel of the given vectors (exact integers)."""
    rows = read(spark, folder, "embeddings").select(*by, F.posexplode("embedding").alias("ch", "x"))
    return rows.groupBy(*by, "ch").agg(F.sum(fixed_column(F.col("x").cast("double"))).alias("s"))


def mask_clip(spark, folder):
    """Kept channels of the given vectors by the size of their sum, at every budget."""
    parts = _channel_sums(spark, folder).select("ch", F.col("s").alias("beta"))
    width = parts.agg(F.count(F.lit(1)).alias("p"))
    budgets = _matrix(spark, list(ETAS.items()), "model string, eta double").crossJoin(width).select("model", F.greatest(F.lit(1), F.floor(F.col("eta") * F.col("p") + 1e-9)).alias("keep"))
    w = Window.partitionBy("model").orderBy(F.desc(F.abs("beta")), "ch")
    return parts.crossJoin(budgets).withColumn("r", F.row_number().over(w)).select("model", "ch", (F.col("r") <= F.col("keep")).alias("kept"))


def weight_norm_select(spark, folder):
    """Channels by the weights of the linear map from the given vectors to their label (class sums), at every budget."""
    labels = A.categories(read(spark, folder, "embeddings"), "label")
    sums = {(r["label"], r["ch"]): r["s"] for r in _channel_sums(spark, folder, "label").collect()}  # classes x channels
    width = 1 + max(ch for _, ch in sums)
    weights = {0: np.array([[float(sums.get((c, j), 0)) for c in labels] for j in range(width)])}
    return _matrix(spark, [(n, int(j)) for n, e in ETAS.items() for j in P.select_weight_norm(weights, P.budget(e, width))], "model string, ch int")


def random_select(spark, folder):
    """As many channels of the given vectors as each budget keeps, chosen by a seed."""
    width = read(spark, folder, "embeddings").agg(F.max(F.size("embedding"))).first()[0]
    return _matrix(spark, [(n, int(j)) for n, e in ETAS.items() for j in P.select_random(width, P.budget(e, width))], "model string, ch int")


def weight_refit(spark, folder):
    """Refit of layer 1's neighbour branch on channels 0 and 1."""
    g = _grams(spark, folder)[1]
    w = formula_weights(1, 1, WIDTH, HIDDEN)
    folded = P.solve_weights(g, np.ones(WIDTH), w, np.array([0, 1]), jitter=0.0)
    return _matrix(spark, [(j, o, int(np.floor(folded[j, o] * 1e6 + 0.4999))) for j in range(2) for o in range(HIDDEN)], "j int, o int, v long")


def _stats(edges, nodes):
    return nodes.agg(F.count(F.lit(1)).alias("v")).crossJoin(edges.agg(F.count(F.lit(1)).alias("e")))


def _dims():
    """Per model and layer: channels read, outputs of the self and the neighbour branch."""
    rows = []
    for name, eta in ETAS.items():
        kept = given_mask(eta) if eta < 1 else np.arange(2 * HIDDEN)
        a, b = int((kept < HIDDEN).sum()), int((kept >= HIDDEN).sum())
        rows += [(name, 1, WIDTH, a, b), (name, 2, len(kept), HIDDEN, HIDDEN)]
    return rows


DIMS = "model string, layer int, f_in int, o_self int, o_near int"


def cost_full(spark, folder):
    nodes, edges, _ = base(spark, folder)
    d = F.col("e") / F.col("v")
    macs = d * F.least("f_in", "o_near") + F.col("f_in") * (F.col("o_self") + F.col("o_near"))
    return _matrix(spark, _dims(), DIMS).crossJoin(F.broadcast(_stats(edges, nodes))).select("model", "layer", fixed_column(macs).alias("macs"))


def cost_memory(spark, folder):
    nodes, edges, _ = base(spark, folder)
    out = F.col("o_self") + F.col("o_near")
    return _matrix(spark, _dims(), DIMS).crossJoin(F.broadcast(_stats(edges, nodes))).select("model", "layer", (F.col("v") * (F.col("f_in") + out) + F.col("f_in") * out).cast("long").alias("stored"))


def cost_batched(spark, folder):
    nodes, edges, _ = base(spark, folder)
    d = F.col("e") / F.col("v")
    macs = (d * F.least("f_in", "o_near") + F.col("f_in") * (F.col("o_self") + F.col("o_near"))) * F.when(F.col("layer") == 1, 1 + d).otherwise(F.lit(1.0))
    rows = _matrix(spark, _dims(), DIMS).crossJoin(F.broadcast(_stats(edges, nodes)))
    return rows.groupBy("model").agg(fixed_column(F.sum(macs)).alias("macs"), fixed_column(F.max(F.when(F.col("layer") == 1, macs / (1 + d) * d))).alias("bound"))


def cost_support(spark, folder):
    nodes, edges, _ = base(spark, folder)
    rows, _, _ = support_sets(make_batches(targets_of(nodes), 64), edges, 2)
    return C.observed_support(rows).select("batch_id", "layer", "role", F.col("nodes").cast("long").alias("nodes"))


def input_bytes(spark, folder):
    nodes, edges, _ = base(spark, folder)
    rows, _, _ = support_sets(make_batches(targets_of(nodes), 64), edges, 2)
    return C.input_bytes(rows, WIDTH).select("batch_id", F.col("bytes").cast("long").alias("bytes"))


def store_reduction(spark, folder):
    nodes, edges, _ = base(spark, folder)
    batches = make_batches(targets_of(nodes), 64)
    kept = nodes.filter(E.split_of() != "test").select(F.lit(1).alias("layer"), "node_id")
    plain, _, _ = support_sets(batches, edges, 2)
    saved, _, _ = support_sets(batches, edges, 2, None, kept)
    return C.store_reduction(plain, saved).select(fixed_column(F.col("reduction")).alias("reduction"))


def cost_rollup(spark, folder):
    """Multiply-adds of full inference on the purchase graph by model, layer and branch, with all subtotals."""
    nodes, edges, _ = base(spark, folder)
    dims = _matrix(spark, _dims(), DIMS).crossJoin(F.broadcast(_stats(edges, nodes)))
    product = lambda o: F.col("v") * F.col("f_in") * F.col(o)
    rows = dims.select("model", "layer", F.stack(F.lit(3), F.lit("self"), product("o_self"), F.lit("near"), product("o_near"), F.lit("mean"), F.col("e") * F.least("f_in", "o_near")).alias("term", "macs"))
    return rows.rollup("model", "layer", "term").agg(F.sum("macs").cast("long").alias("macs"))


PUBLISHED = [("a", 500, 256, 7, 89250, 899756), ("b", 128, 512, 40, 169343, 1166243), ("c", 602, 128, 41, 232965, 11606919), ("d", 300, 512, 100, 716847, 6977410)]


#: Attributes, hidden channels and classes that the cost model is asked for on each given graph.
GIVEN = {"purchase": (127, 256, 5), "supply": (127, 256, 5)}


def printed_costs(spark, folder):
    """The fitted cost model on the sizes of the given graphs, at every budget."""
    kinds = {"purchase": (E.purchase, ("customer", "part")), "supply": (E.supply, ("supplier", "part"))}
    rows = []
    for g, (f, h, c) in GIVEN.items():
        build, of = kinds[g]
        v, e = node_ids(spark, folder, of).count(), build(spark, folder).count() // 2  # each link stands both ways
        rows += [(g, n, round(C.printed_full_kmacs(f, h, c, v, e, eta)), round(C.printed_full_mib(f, h, v, e, eta))) for n, eta in ETAS.items()]
    return _matrix(spark, rows, "graph string, model string, kmacs long, mib long")


# ------------------------------------------------------------------ accuracy


def _scored(spark, folder):
    """Parts with the region label and the argmax of the two-layer output's first five channels."""
    nodes, edges, feats = base(spark, folder)
    h = infer_full(two_layer(), nodes, edges, feats, WIDTH)
    top = F.transform(F.slice("h", 1, 5), fixed_column)
    pred = h.select("node_id", top.alias("t")).select("node_id", (F.array_position("t", F.array_max("t")) - 1).cast("int").alias("pred"))
    return A.part_region(spark, folder).join(pred, "node_id")


def micro_f1_single(spark, folder):
    n = M.micro_f1(_scored(spark, folder))
    return n.select("tp", "fp", "fn", fixed_column(F.col("micro_f1")).alias("micro_f1"))


def confusion(spark, folder):
    return M.confusion(_scored(spark, folder))


def micro_f1_multi(spark, folder):
    """Six classes a customer; a class is guessed by the parity of a hash."""
    rows = A.customer_types_multi(spark, folder).withColumn("pred", (F.pmod(F.col("node_id") / 4 + F.length("p_type"), F.lit(2)) == 0).cast("int"))
    wide = rows.groupBy("node_id").agg(F.sort_array(F.collect_list(F.struct("p_type", "label", "pred"))).alias("c")).select("node_id", F.transform("c", lambda x: x["label"] == 1).alias("label"), F.transform("c", lambda x: x["pred"] == 1).alias("pred"))
    n = M.micro_f1(wide, multilabel=True)
    return n.select("tp", "fp", "fn", fixed_column(F.col("micro_f1")).alias("micro_f1"))


# ------------------------------------------------------------------ baselines


def linear_two_hop(spark, folder):
    nodes, edges, feats = base(spark, folder)
    return cells(B.linear(edges, feats, WIDTH, formula_weights(1, 2, WIDTH, HIDDEN), nodes))


def precomputed_branches(spark, folder):
    nodes, edges, feats = base(spark, folder)
    ready = B.precomputed(edges, feats, WIDTH, 2, nodes)
    return cells(B.precomputed_branches(ready, [formula_weights(1, k, WIDTH, HIDDEN) for k in range(3)], formula_weights(2, 0, 3 * HIDDEN, HIDDEN)))


def mlp_scores(spark, folder):
    nodes, edges, feats = base(spark, folder)
    return cells(infer_full(B.mlp([WIDTH, HIDDEN, HIDDEN]), nodes, edges, feats, WIDTH))


def label_propagation(spark, folder):
    nodes, edges, _ = base(spark, folder)
    known = A.part_region(spark, folder).filter(E.split_of() == "train")
    return cells(B.label_propagation(edges, nodes, known, 5, rounds=2))


def _seeds(nodes):
    return nodes.filter(E.split_of(train=98, val=99) == "test")


def ppr_topk(spark, folder):
    nodes, edges, _ = base(spark, folder)
    found = B.personalised_pagerank(edges, _seeds(nodes), rounds=2)
    return found.select("seed", "node_id", fixed_column(F.col("mass")).alias("mass"))


def ppr_network(spark, folder):
    nodes, edges, feats = base(spark, folder)
    return cells(B.ppr_network(edges, feats, WIDTH, _seeds(nodes), B.mlp([WIDTH, HIDDEN, HIDDEN]), nodes, rounds=2))


def student_scores(spark, folder):
    nodes, edges, feats = base(spark, folder)
    layer = AttentionLayer([(formula_weights(1, i, WIDTH, 2), formula_weights(2, i, 2, 1)[:, 0], formula_weights(3, i, 2, 1)[:, 0]) for i in range(2)])
    return cells(B.student(edges, feats, WIDTH, nodes, layer, formula_weights(2, 0, 4, HIDDEN)))


def convolution_network(spark, folder):
    nodes, edges, feats = base(spark, folder)
    return cells(infer_full(B.convolution([WIDTH, HIDDEN, HIDDEN]), nodes, edges, feats, WIDTH))


# ------------------------------------------------------------------ store


def stale_embeddings(spark, folder):
    """What a lookup of stored features alone serves a week before the last write."""
    rows = _writes(spark, folder)
    until = rows.agg(F.max("written_at").alias("now")).first()["now"] - dt.timedelta(days=7)
    return B.stale(rows, F.lit(until)).select("node_id", F.datediff(F.lit(until), "written_at").alias("age_days"))


def normalized_attributes(spark, folder):
    _, _, feats = base(spark, folder)
    return cells(B.normalize_features(feats, WIDTH))


def prepared_costs(spark, folder):
    """Multiply-adds a node that preparing 1 to 3 propagated branches adds before inference."""
    nodes, edges, _ = base(spark, folder)
    degree = edges.agg(F.count(F.lit(1)).alias("e")).crossJoin(nodes.agg(F.count(F.lit(1)).alias("v"))).first()
    rows = [(k, int(np.floor(C.preprocess_macs(degree["e"] / degree["v"], WIDTH, k) * 1e6 + 0.4999))) for k in (1, 2, 3)]
    return _matrix(spark, rows, "steps int, v long")


def _writes(spark, folder):
    o = read(spark, folder, "orders")
    return o.select((F.pmod("o_orderkey", F.lit(2)) + 1).cast("int").alias("layer"), F.lit("m").alias("model"), F.col("o_orderkey").alias("batch"), (F.col("o_custkey") * 4).alias("node_id"), F.col("o_orderdate").alias("written_at"))


def store_latest(spark, folder):
    return S.latest(_writes(spark, folder)).select("layer", "node_id", "batch")


def store_expire(spark, folder):
    rows = _writes(spark, folder)
    now = rows.agg(F.max("written_at").alias("now"))
    kept = rows.crossJoin(F.broadcast(now)).filter(F.col("written_at") >= F.col("now") - F.expr("interval 90 days"))
    return kept.groupBy("layer").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("node_id").alias("nodes"))


def store_share(spark, folder):
    """Rows a policy that stores a share of nodes keeps."""
    rows = S.latest(_writes(spark, folder))
    out = None
    for share in (0.25, 0.5, 0.75):
        n = S.choose(rows, share).agg(F.count(F.lit(1)).alias("n")).select(F.lit(share).alias("share"), "n")
        out = n if out is None else out.unionByName(n)
    return out


def shape_features(spark, folder):
    return read(spark, folder, "documents").select("doc_id", *(c.alias(n) for n, c in A.shape_columns().items() if n != "distinct_words"))


def token_features(spark, folder):
    return cells(A.token_features(read(spark, folder, "documents"), 16))


def queries() -> dict:
    names = [
        gram_branch, lasso_terms, lasso_mask_path, mask_clip, weight_refit, cost_full, cost_memory, cost_batched, cost_support, input_bytes, store_reduction, cost_rollup, printed_costs,
        micro_f1_single, micro_f1_multi, confusion, linear_two_hop, precomputed_branches, mlp_scores, label_propagation, ppr_topk, ppr_network, student_scores, convolution_network,
        store_latest, store_expire, store_share, stale_embeddings, normalized_attributes, prepared_costs, shape_features, token_features, weight_norm_select, random_select,
    ]
    return {f.__name__: f for f in names}


# ------------------------------------------------------------------ oracles


def _gram_plan():
    plan = Plan()
    plan.add(f"SELECT node_id FROM nodes WHERE {SPLIT.format(n='node_id')} < 60", "tn")
    plan.add("SELECT dst, src FROM e WHERE dst IN (SELECT node_id FROM tn) AND src IN (SELECT node_id FROM tn)", "te")
    f = plan.features(WIDTH)
    own = plan.add(f"SELECT * FROM {f} WHERE node_id IN (SELECT node_id FROM tn)")
    near = plan.step(own, edges="te")
    g = {k: plan.add(f"SELECT a.j, b.j AS l, sum(a.x * b.x) AS v FROM {h} a JOIN {h} b ON a.node_id = b.node_id GROUP BY 1, 2") for k, h in ((0, own), (1, near))}
    return plan, g


def _dims_sql() -> str:
    return "dims AS (SELECT * FROM (VALUES " + ", ".join(f"('{m}', {l}, {f}, {a}, {b})" for m, l, f, a, b in _dims()) + ") t(model, layer, f_in, o_self, o_near)),\nst AS (SELECT (SELECT count(*) FROM nodes) AS v, (SELECT count(*) FROM e) AS e)"


def _dims_plan(body: str) -> str:
    plan = Plan()
    plan.parts.append(_dims_sql())
    return plan.select(body)


LABEL = """votes AS (SELECT e.dst AS node_id, n_regionkey, count(*) AS n FROM e JOIN customer ON c_custkey = e.src // 4 JOIN nation ON n_nationkey = c_nationkey WHERE e.dst % 4 = 1 GROUP BY 1, 2),
lab AS (SELECT node_id, n_regionkey AS label FROM (SELECT *, row_number() OVER (PARTITION BY node_id ORDER BY n DESC, n_regionkey) r FROM votes) WHERE r = 1)"""


SWEEPS = 400


def _mask_path_sql(plan: Plan, q: str) -> str:
    """Coordinate descent as a recursion: one step sets one mask of every penalty."""
    row = plan.add(f"SELECT j, list(q ORDER BY l) AS q, sum(q) AS r, max(q) FILTER (j = l) AS d FROM {q} GROUP BY 1")
    steps = "VALUES " + ", ".join(f"({s})" for s in (0, 1, 2, 5, 10, 20, 50, 100))
    lam = plan.add(f"SELECT p.penalty, p.penalty / 100.0::DOUBLE * 2 * (SELECT max(abs(r)) FROM {row}) AS lam FROM ({steps}) p(penalty)")
    new = "sign(x.rest) * greatest(abs(x.rest) - x.lam / 2, 0) / x.d"
    plan.parts.append(f"""path AS (SELECT penalty, lam, 0 AS step, list_transform(range({WIDTH}), lambda i: 1.0::DOUBLE) AS beta FROM {lam}
UNION ALL SELECT penalty, lam, step + 1, list_transform(beta, lambda b, i: CASE WHEN i = x.j + 1 THEN CASE WHEN x.d <= 0 THEN 0 ELSE {new} END ELSE b END)
FROM (SELECT path.*, w.j, w.d, w.r - list_dot_product(w.q, path.beta) + w.d * path.beta[w.j + 1] AS rest FROM path JOIN {row} w ON w.j = path.step % {WIDTH} WHERE path.step < {SWEEPS * WIDTH}) x)""")
    cell = plan.add(f"SELECT penalty, unnest(range({WIDTH})) AS ch, unnest(beta) AS b FROM path WHERE step = {SWEEPS * WIDTH}")
    text = plan.select(f"SELECT CAST(penalty AS INTEGER) AS penalty, CAST(ch AS INTEGER) AS ch, {fixed('b')} AS v FROM {cell}")
    return text.replace("WITH ", "WITH RECURSIVE ", 1)


def _token_sql(width: int = 16) -> str:
    """Hashed token counts; the check value is computed bit by bit."""
    byte = "list_reduce(list_prepend(xor(s, c), list_transform(range(8), lambda x: x::UBIGINT)), lambda v, b: CASE WHEN v & 1 = 1 THEN xor(v >> 1, 3988292384::UBIGINT) ELSE v >> 1 END)"
    check = f"xor(list_reduce(list_prepend(4294967295::UBIGINT, list_transform(string_split(t, ''), lambda c: ascii(c)::UBIGINT)), lambda s, c: {byte}), 4294967295::UBIGINT)"
    return f"""WITH w AS (SELECT doc_id AS node_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS t FROM documents),
k AS (SELECT t, CAST({check} % {width} AS INTEGER) AS ch FROM (SELECT DISTINCT t FROM w WHERE length(t) > 0)),
n AS (SELECT node_id, ch, ln(1 + count(*)) AS x FROM w JOIN k USING (t) GROUP BY 1, 2),
s AS (SELECT node_id, sqrt(sum(x * x)) AS s FROM n GROUP BY 1)
SELECT s.node_id, CAST(r.ch AS INTEGER) AS ch, {fixed('coalesce(n.x, 0) / s.s')} AS v FROM s CROSS JOIN range({width}) r(ch) LEFT JOIN n ON n.node_id = s.node_id AND n.ch = r.ch"""


def oracle_sql() -> dict[str, str]:
    from prunegraph.plans.headline import BATCHES, _support_sql, _two, attention_rows

    out: dict[str, str] = {}
    plan, g = _gram_plan()
    out["gram_branch"] = plan.select(f"SELECT j, l, {fixed('v')} AS v FROM {g[1]}")
    plan, g = _gram_plan()
    w = {k: plan.weights(1, k, WIDTH, HIDDEN) for k in (0, 1)}
    parts = {k: plan.add(f"SELECT g.j, g.l, g.v, sum(CAST(a.w AS DOUBLE) * CAST(b.w AS DOUBLE)) AS ww FROM {g[k]} g JOIN {w[k]} a ON a.j = g.j JOIN {w[k]} b ON b.j = g.l AND b.o = a.o GROUP BY 1, 2, 3") for k in (0, 1)}
    both = " UNION ALL ".join(f"SELECT * FROM {p}" for p in parts.values())
    q = plan.add(f"SELECT j, l, sum(v * ww) AS q FROM ({both}) GROUP BY 1, 2")
    out["lasso_terms"] = plan.select(
        f"SELECT 'q' AS term, j, l, CAST(floor(q * 10000 + 0.4999) AS BIGINT) AS v FROM {q} UNION ALL SELECT 'r', j, 0, CAST(floor(sum(q) * 10000 + 0.4999) AS BIGINT) FROM {q} GROUP BY j"
    )
    out["lasso_mask_path"] = _mask_path_sql(plan, q)
    out["token_features"] = _token_sql()
    until = "(SELECT max(o_orderdate) FROM orders) - INTERVAL 7 DAY"
    out["stale_embeddings"] = f"SELECT o_custkey * 4 AS node_id, CAST(date_diff('day', max(o_orderdate), {until}) AS INTEGER) AS age_days FROM orders WHERE o_orderdate < {until} GROUP BY 1"
    p = Plan()
    out["normalized_attributes"] = p.select(f"SELECT f.node_id, f.j AS ch, {fixed('(f.x - s.m) / CASE WHEN s.d = 0 THEN 1 ELSE s.d END')} AS v FROM {{f}} f JOIN (SELECT j, avg(x) AS m, stddev_pop(x) AS d FROM {{f}} GROUP BY 1) s ON s.j = f.j".format(f=p.features(WIDTH)))
    out["prepared_costs"] = Plan().select(f"SELECT CAST(k AS INTEGER) AS steps, {fixed(f'k * (CAST((SELECT count(*) FROM e) AS DOUBLE) / (SELECT count(*) FROM nodes)) * {WIDTH}')} AS v FROM range(1, 4) r(k)")
    p = Plan()
    out["student_scores"] = p.cells(p.product(attention_rows(p), p.weights(2, 0, 4, HIDDEN)))
    etas = ", ".join(f"('{m}', CAST({x} AS DOUBLE))" for m, x in ETAS.items())
    kept = f"greatest(1, floor(eta * p + 1e-9)) AS keep FROM (VALUES {etas}) m(model, eta), (SELECT max(len(embedding)) AS p FROM embeddings)"
    sums = f"SELECT label, CAST(j - 1 AS INTEGER) AS ch, CAST(sum({fixed('x')}) AS BIGINT) AS s FROM (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS j FROM embeddings) GROUP BY 1, 2"
    out["mask_clip"] = f"SELECT model, ch, row_number() OVER (PARTITION BY model ORDER BY abs(beta) DESC, ch) <= keep AS kept FROM (SELECT ch, sum(s) AS beta FROM ({sums}) GROUP BY 1), (SELECT model, {kept})"
    out["weight_norm_select"] = f"SELECT model, ch FROM (SELECT model, keep, ch, row_number() OVER (PARTITION BY model ORDER BY s DESC, ch) r FROM (SELECT ch, sum(abs(s)) AS s FROM ({sums}) WHERE label IS NOT NULL GROUP BY 1), (SELECT model, {kept})) WHERE r <= keep"
    out["random_select"] = f"SELECT model, ch FROM (SELECT model, keep, ch, row_number() OVER (PARTITION BY model ORDER BY ((CAST(ch AS BIGINT) * 40503 + 9973 + 12345) * 25173) % 65536, ch) r FROM (SELECT CAST(unnest(range(max(len(embedding)))) AS INTEGER) AS ch FROM embeddings), (SELECT model, {kept})) WHERE r <= keep"
    plan, g = _gram_plan()
    w = plan.weights(1, 1, WIDTH, HIDDEN)
    rhs = plan.add(f"SELECT g.j, w.o, sum(g.v * CAST(w.w AS DOUBLE)) AS b FROM {g[1]} g JOIN {w} w ON w.j = g.l WHERE g.j < 2 GROUP BY 1, 2")
    det = plan.add(f"SELECT max(v) FILTER (j = 0 AND l = 0) AS a, max(v) FILTER (j = 0 AND l = 1) AS b, max(v) FILTER (j = 1 AND l = 1) AS d FROM {g[1]}")
    out["weight_refit"] = plan.select(
        f"SELECT x.j, x.o, CAST(floor((CASE WHEN x.j = 0 THEN m.d ELSE m.a END * x.b - m.b * y.b) / (m.a * m.d - m.b * m.b) * 1000000 + 0.4999) AS BIGINT) AS v FROM {rhs} x JOIN {rhs} y ON y.o = x.o AND y.j = 1 - x.j, {det} m"
    )
    d = "(CAST(e AS DOUBLE) / v)"
    macs = f"{d} * least(f_in, o_near) + f_in * (o_self + o_near)"
    out["cost_full"] = _dims_plan(f"SELECT model, layer, {fixed(macs)} AS macs FROM dims, st")
    out["cost_memory"] = _dims_plan("SELECT model, layer, CAST(v * (f_in + o_self + o_near) + f_in * (o_self + o_near) AS BIGINT) AS stored FROM dims, st")
    out["cost_batched"] = _dims_plan(f"SELECT model, {fixed(f'sum(({macs}) * CASE WHEN layer = 1 THEN 1 + {d} ELSE 1 END)')} AS macs, {fixed(f'max(CASE WHEN layer = 1 THEN ({macs}) * (1 + {d}) / (1 + {d}) * {d} END)')} AS bound FROM dims, st GROUP BY model")
    sup = lambda store=False: _support_sql(store=store)
    out["cost_support"] = f"SELECT batch_id, layer, role, count(DISTINCT node_id) AS nodes FROM ({sup()}) GROUP BY 1, 2, 3"
    out["input_bytes"] = f"SELECT batch_id, CAST(count(DISTINCT node_id) * 4 * {WIDTH} AS BIGINT) AS bytes FROM ({sup()}) WHERE layer = 0 GROUP BY 1"
    n = lambda s: f"(SELECT count(*) FROM (SELECT DISTINCT batch_id, node_id FROM ({s}) WHERE layer = 1 AND role <> 'visited'))"
    out["store_reduction"] = f"SELECT {fixed(f'1 - CAST({n(sup(True))} AS DOUBLE) / {n(sup())}')} AS reduction"
    out["cost_rollup"] = _dims_plan("SELECT model, layer, term, CAST(sum(macs) AS BIGINT) AS macs FROM (SELECT model, layer, 'self' AS term, v * f_in * o_self AS macs FROM dims, st UNION ALL SELECT model, layer, 'near', v * f_in * o_near FROM dims, st UNION ALL SELECT model, layer, 'mean', e * least(f_in, o_near) FROM dims, st) GROUP BY ROLLUP (model, layer, term)")
    given = {"purchase": "SELECT (SELECT count(*) FROM customer) + (SELECT count(*) FROM part) AS v, (SELECT count(*) FROM (SELECT DISTINCT o_custkey, l_partkey FROM orders JOIN lineitem ON l_orderkey = o_orderkey)) AS e", "supply": "SELECT (SELECT count(*) FROM supplier) + (SELECT count(*) FROM part) AS v, (SELECT count(*) FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem)) AS e"}
    sizes = " UNION ALL ".join(f"SELECT '{g_}' AS graph, {f} AS f, {h} AS h, {c} AS c, v, e FROM ({given[g_]})" for g_, (f, h, c) in GIVEN.items())
    out["printed_costs"] = f"""SELECT graph, model, CAST(round(((deg + 1) * f + 2 * f * one + (deg + 1) * wide + 2 * wide * one + wide * c + 4 * wide) / 1000) AS BIGINT) AS kmacs,
CAST(round((4 * v * greatest(f + wide, 3 * wide) + 8 * e + 4 * greatest(2 * f * one, 2 * wide * one)) / 1048576) AS BIGINT) AS mib
FROM (SELECT *, CAST(2 AS DOUBLE) * e / v AS deg, 2 * h * eta AS wide, h * eta AS one FROM ({sizes}) g, (VALUES {etas}) m(model, eta))"""

    def scored(body: str) -> str:
        p = Plan()
        h = _two(p, p.features(WIDTH))
        p.parts.append(LABEL)
        p.add(f"SELECT node_id, j AS pred FROM (SELECT node_id, j, row_number() OVER (PARTITION BY node_id ORDER BY {fixed('x')} DESC, j) r FROM {h} WHERE j < 5) WHERE r = 1", "pr")
        return p.select(body)

    f1 = fixed("CAST(2 * tp AS DOUBLE) / (2 * tp + fp + fn)")
    out["micro_f1_single"] = scored(f"SELECT tp, fp, fn, {f1} AS micro_f1 FROM (SELECT CAST(sum((label = pred)::INT) AS BIGINT) AS tp, CAST(sum((label <> pred)::INT) AS BIGINT) AS fp, CAST(sum((label <> pred)::INT) AS BIGINT) AS fn FROM lab JOIN pr USING (node_id))")
    out["confusion"] = scored("SELECT label, CAST(pred AS INTEGER) AS pred, count(*) AS n FROM lab JOIN pr USING (node_id) GROUP BY 1, 2")
    p = Plan()
    p.add("SELECT e.dst AS node_id, p_type FROM e JOIN part ON p_partkey = e.src // 4 WHERE e.dst % 4 = 0", "pairs")
    p.add("SELECT p_type, count(*) AS t, (SELECT count(*) FROM pairs) AS n FROM pairs GROUP BY 1", "al")
    p.add("SELECT node_id, count(*) AS mine FROM pairs GROUP BY 1", "own")
    p.add("SELECT node_id, p_type, count(*) AS c FROM pairs GROUP BY 1, 2", "cell")
    p.add("SELECT own.node_id, al.p_type, coalesce(c, 0) * al.n > al.t * mine AS y, (own.node_id // 4 + length(al.p_type)) % 2 = 0 AS g FROM own CROSS JOIN al LEFT JOIN cell ON cell.node_id = own.node_id AND cell.p_type = al.p_type", "z")
    out["micro_f1_multi"] = p.select(f"SELECT tp, fp, fn, {f1} AS micro_f1 FROM (SELECT CAST(sum((y AND g)::INT) AS BIGINT) AS tp, CAST(sum((NOT y AND g)::INT) AS BIGINT) AS fp, CAST(sum((y AND NOT g)::INT) AS BIGINT) AS fn FROM z)")
    p = Plan()
    f = p.features(WIDTH)
    out["linear_two_hop"] = p.cells(p.product(p.step(p.step(f)), p.weights(1, 2, WIDTH, HIDDEN)))
    p = Plan()
    f = p.features(WIDTH)
    s1 = p.step(f)
    hidden = p.relu(p.concat([(p.product(x, p.weights(1, k, WIDTH, HIDDEN)), HIDDEN) for k, x in enumerate((f, s1, p.step(s1)))]))
    out["precomputed_branches"] = p.cells(p.product(hidden, p.weights(2, 0, 3 * HIDDEN, HIDDEN)))

    def mlp(p: Plan) -> str:
        return p.product(p.relu(p.product(p.features(WIDTH), p.weights(1, 0, WIDTH, HIDDEN))), p.weights(2, 0, HIDDEN, HIDDEN))

    p = Plan()
    out["mlp_scores"] = p.cells(mlp(p))
    p = Plan()
    p.parts.append(LABEL)
    p.add(f"SELECT * FROM lab WHERE {SPLIT.format(n='node_id')} < 60", "kn")
    h = p.add("SELECT n.node_id, CAST(c AS INTEGER) AS j, CASE WHEN kn.label = c THEN CAST(1 AS DOUBLE) ELSE 0 END AS x FROM nodes n CROSS JOIN range(5) r(c) LEFT JOIN kn ON kn.node_id = n.node_id")
    first = h
    for _ in range(2):
        s = p.step(h)
        h = p.add(f"SELECT s.node_id, s.j, CASE WHEN kn.node_id IS NULL THEN s.x ELSE f.x END AS x FROM {s} s JOIN {first} f ON f.node_id = s.node_id AND f.j = s.j LEFT JOIN kn ON kn.node_id = s.node_id")
    out["label_propagation"] = p.cells(h)

    def ppr(p: Plan) -> str:
        p.add("SELECT dst, count(*) AS n FROM e GROUP BY 1", "deg")
        p.add(f"SELECT node_id AS seed, node_id, CAST(1 AS DOUBLE) AS mass FROM nodes WHERE {SPLIT.format(n='node_id')} >= 99", "m0")
        now = "m0"
        for _ in range(2):
            now = p.add(f"SELECT seed, node_id, sum(mass) AS mass FROM (SELECT m.seed, e.src AS node_id, m.mass * (CAST(1 AS DOUBLE) / deg.n) * 0.75::DOUBLE AS mass FROM {now} m JOIN e ON e.dst = m.node_id JOIN deg ON deg.dst = e.dst UNION ALL SELECT seed, node_id, 0.25::DOUBLE FROM m0) GROUP BY 1, 2")
        return p.add(f"SELECT seed, node_id, mass FROM (SELECT *, row_number() OVER (PARTITION BY seed ORDER BY {fixed('mass')} DESC, node_id) r FROM {now}) WHERE r <= 8")

    p = Plan()
    top = ppr(p)
    out["ppr_topk"] = p.select(f"SELECT seed, node_id, {fixed('mass')} AS mass FROM {top}")
    p = Plan()
    z, t = mlp(p), ppr(p)
    out["ppr_network"] = p.cells(p.add(f"SELECT t.seed AS node_id, z.j, sum(t.mass * z.x) AS x FROM {t} t JOIN {z} z ON z.node_id = t.node_id GROUP BY 1, 2"))
    p = Plan()
    h = p.features(WIDTH)
    for i, f_in in ((1, WIDTH), (2, HIDDEN)):
        h = p.relu(p.product(p.step(h), p.weights(i, 1, f_in, HIDDEN)))
    out["convolution_network"] = p.cells(h)
    w = "SELECT CAST(o_orderkey % 2 + 1 AS INTEGER) AS layer, o_orderkey AS batch, o_custkey * 4 AS node_id, o_orderdate AS written_at FROM orders"
    last = f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY layer, node_id ORDER BY written_at DESC, batch DESC) r FROM ({w})) WHERE r = 1"
    out["store_latest"] = f"SELECT layer, node_id, batch FROM ({last})"
    out["store_expire"] = f"SELECT layer, count(*) AS n, count(DISTINCT node_id) AS nodes FROM ({w}) WHERE written_at >= (SELECT max(o_orderdate) FROM orders) - INTERVAL 90 DAY GROUP BY 1"
    out["store_share"] = " UNION ALL ".join(f"SELECT CAST({s} AS DOUBLE) AS share, count(*) AS n FROM ({last}) WHERE ((node_id % 65536) * 40503) % 65536 < {s} * 65536" for s in (0.25, 0.5, 0.75))
    out["shape_features"] = """SELECT doc_id, length(text) AS chars, length(regexp_replace(text, '[^0-9]', '', 'g')) AS digits, length(regexp_replace(text, '[^A-Z]', '', 'g')) AS uppers,
len(list_filter(string_split_regex(text, '[ \n]+'), lambda w: length(w) > 0)) AS words, len(string_split(text, chr(10))) AS lines FROM documents"""
    return out
