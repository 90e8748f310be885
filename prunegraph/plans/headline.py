"""Graphs, layers, full and batched inference, pruning on given masks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prunegraph.functions.attributes import formula_features
from prunegraph.operators import edges as E
from prunegraph.operators.layers import AttentionLayer, GraphLayer, Network, formula_weights, infer_full, presets
from prunegraph.operators.propagate import normalize, propagate, propagate_k, to_long
from prunegraph.operators.support import infer_batched, make_batches, support_sets
from prunegraph.plans.sqltext import SPLIT, Plan, fixed
from prunegraph.sources.tables import node_ids

WIDTH, HIDDEN = 8, 4


def fixed_column(c):
    """Millionths of a double, away from ties."""
    return F.floor(c * 1000000 + 0.4999).cast("long")


def cells(feats: DataFrame) -> DataFrame:
    return to_long(feats.select("node_id", "h")).select("node_id", "ch", fixed_column(F.col("x")).alias("v"))


def base(spark: SparkSession, folder: str):
    """Purchase graph: nodes, edges, formula features."""
    nodes = node_ids(spark, folder)
    return nodes, E.purchase(spark, folder), formula_features(nodes, WIDTH)


def _edges(build, *also):
    return lambda spark, folder: build(spark, folder)


def _layer(layer):
    def run(spark, folder):
        nodes, edges, feats = base(spark, folder)
        return cells(layer.forward(nodes, edges, feats, WIDTH))

    return run


def _of(k_min, k_max, **how):
    return GraphLayer({k: formula_weights(1, k, WIDTH, HIDDEN) for k in range(k_min, k_max + 1)}, **how)


def _attention() -> AttentionLayer:
    heads = [(formula_weights(1, i, WIDTH, 2), formula_weights(2, i, 2, 1)[:, 0], formula_weights(3, i, 2, 1)[:, 0]) for i in range(2)]
    return AttentionLayer(heads)


def two_layer() -> Network:
    return presets.self_and_mean([WIDTH, HIDDEN, HIDDEN])


def forward_two_layer(spark, folder):
    nodes, edges, feats = base(spark, folder)
    return cells(infer_full(two_layer(), nodes, edges, feats, WIDTH))


def jumping_two_layer(spark, folder):
    nodes, edges, feats = base(spark, folder)
    return cells(infer_full(presets.jumping([WIDTH, HIDDEN, HIDDEN]), nodes, edges, feats, WIDTH))


# ------------------------------------------------------------------ given masks


def given_mask(eta: float) -> np.ndarray:
    """Kept outputs of layer 1 by a rule: least (5j + 3) mod 8 first."""
    keep = max(1, int(eta * 2 * HIDDEN))
    order = sorted(range(2 * HIDDEN), key=lambda j: ((5 * j + 3) % 8, j))
    return np.array(sorted(order[:keep]))


def masked_full(eta: float) -> Network:
    """Layer 2 reads the kept channels, layer 1 no longer makes the others."""
    net, kept = two_layer(), given_mask(eta)
    first, second = net.layers
    first.weights = {0: first.weights[0][:, kept[kept < HIDDEN]], 1: first.weights[1][:, kept[kept >= HIDDEN] - HIDDEN]}
    second.weights = {k: w[kept] for k, w in second.weights.items()}
    return net


def masked_batched(eta: float) -> Network:
    """As ``masked_full``; layer 1's neighbour branch also reads fewer attributes."""
    net, kept = masked_full(eta), [int(j) for j in given_mask(eta)]
    first = net.layers[0]
    first.weights = {**first.weights, 1: first.weights[1][kept]}
    first.kept_branch = {1: kept}
    return net


def _pruned_full(eta):
    def run(spark, folder):
        nodes, edges, feats = base(spark, folder)
        return cells(infer_full(masked_full(eta), nodes, edges, feats, WIDTH))

    return run


def targets_of(nodes: DataFrame) -> DataFrame:
    return nodes.filter(E.split_of() == "test")


def _batched(net, store=False, caps=None):
    def run(spark, folder):
        nodes, edges, feats = base(spark, folder)
        batches = make_batches(targets_of(nodes), 64)
        kept = None
        if store:
            first = two_layer().layers[0].forward(nodes, edges, feats, WIDTH)
            kept = first.filter(E.split_of() != "test").select(F.lit(1).alias("layer"), "node_id", "h")
        found = infer_batched(net, batches, edges, feats, WIDTH, caps=caps, store=kept)
        return to_long(found.select("batch_id", "node_id", "h")).select("batch_id", "node_id", "ch", fixed_column(F.col("x")).alias("v"))

    return run


def batches(spark, folder):
    nodes = node_ids(spark, folder)
    return make_batches(targets_of(nodes), 64)


def _support(caps=None, store=False):
    def run(spark, folder):
        nodes, edges, _ = base(spark, folder)
        kept = nodes.filter(E.split_of() != "test").select(F.lit(1).alias("layer"), "node_id") if store else None
        rows, _, _ = support_sets(make_batches(targets_of(nodes), 64), edges, 2, caps, kept)
        return rows

    return run


def degree(how):
    def run(spark, folder):
        e = normalize(E.purchase(spark, folder), how)
        return e.select("dst", "src", fixed_column(F.col("w")).alias("v"))

    return run


def steps(k, layout="auto"):
    def run(spark, folder):
        nodes, edges, feats = base(spark, folder)
        return cells(propagate_k(edges, feats, k, WIDTH, nodes, layout=layout)[k])

    return run


def replicated(spark, folder):
    nodes = node_ids(spark, folder)
    _, links = E.replicate(nodes, E.purchase(spark, folder), 3, 1_000_000)
    return links


def queries() -> dict:
    return {
        "edges_purchase": E.purchase,
        "edges_copurchase": E.copurchase,
        "edges_chain": E.chain,
        "edges_supply": E.supply,
        "edges_event": E.same_user_events,
        "edges_reply": E.replies,
        "edges_doc": E.rare_tokens,
        "edges_knn": E.nearest_vectors,
        "hyperlink_edges": E.hyperlinks,
        "replicate_graph": replicated,
        "degree_row_mean": degree("row_mean"),
        "degree_sym": degree("sym"),
        "degree_self_loop": degree("self_loop_mean"),
        "propagate_1": steps(1),
        "propagate_2": steps(2),
        "propagate_array_layout": steps(1, "array"),
        "propagate_long_layout": steps(1, "long"),
        "layer_convolution": _layer(_of(1, 1)),
        "layer_self_mean": _layer(_of(0, 1)),
        "layer_multi_order": _layer(_of(0, 2)),
        "layer_dense": _layer(_of(0, 0)),
        "layer_mean_combine": _layer(_of(0, 1, combine="mean")),
        "layer_residual": _layer(GraphLayer({k: formula_weights(1, k, WIDTH, WIDTH // 2) for k in (0, 1)}, residual=True)),
        "layer_attention": _layer(_attention()),
        "multiply_first": _layer(_of(0, 1, order="mul_first")),
        "aggregate_first": _layer(_of(0, 1, order="agg_first")),
        "forward_two_layer": forward_two_layer,
        "forward_jumping": jumping_two_layer,
        "batch_former": batches,
        "support_two_hop": _support(),
        "support_capped": _support(caps={2: 4}),
        "support_with_store": _support(store=True),
        "batched_two_layer": _batched(two_layer()),
        "batched_capped": _batched(two_layer(), caps={2: 4}),
        "batched_with_store": _batched(two_layer(), store=True),
        **{f"pruned_forward_{n}x": _pruned_full(1 / n) for n in (2, 4, 8)},
        **{f"pruned_batched_{n}x": _batched(masked_batched(1 / n)) for n in (2, 4, 8)},
    }


# ------------------------------------------------------------------ oracles


def _two(plan: Plan, h: str) -> str:
    first = plan.layer(h, 1, range(0, 2), WIDTH, HIDDEN)
    return plan.layer(first, 2, range(0, 2), 2 * HIDDEN, HIDDEN)


def _masked(plan: Plan, h: str, eta: float, branch: bool) -> str:
    kept = [int(j) for j in given_mask(eta)]
    list_ = ", ".join(map(str, kept))
    w0, w1 = plan.weights(1, 0, WIDTH, HIDDEN), plan.weights(1, 1, WIDTH, HIDDEN)
    if branch:
        w1 = plan.add(f"SELECT * FROM {w1} WHERE j IN ({list_})")
    first = plan.relu(plan.concat([(plan.product(h, w0), HIDDEN), (plan.product(plan.step(h), w1), HIDDEN)]))
    left = plan.add(f"SELECT * FROM {first} WHERE j IN ({list_})")
    parts = [(plan.product(x, plan.weights(2, k, 2 * HIDDEN, HIDDEN)), HIDDEN) for k, x in ((0, left), (1, plan.step(left)))]
    return plan.relu(plan.concat(parts))


BATCHES = f"""ranked AS (SELECT node_id, row_number() OVER (ORDER BY ((node_id % 65536) * 40503) % 65536, node_id) - 1 AS r FROM nodes WHERE {SPLIT.format(n='node_id')} >= 75),
batches AS (SELECT CAST(r // 64 AS INTEGER) AS batch_id, node_id FROM ranked)"""


def _support_sql(cap: int | None = None, store: bool = False, select: bool = True):
    plan = Plan()
    plan.parts.append(BATCHES)
    plan.add(f"SELECT node_id FROM nodes WHERE {SPLIT.format(n='node_id')} < 75", "kept")
    plan.add("SELECT batch_id, dst, src FROM batches b JOIN e ON e.dst = b.node_id", "e2")
    plan.add("SELECT DISTINCT batch_id, src AS node_id FROM e2 EXCEPT SELECT batch_id, node_id FROM batches", "near")
    plan.add("SELECT * FROM near WHERE node_id IN (SELECT node_id FROM kept)" if store else "SELECT * FROM near WHERE false", "visited")
    plan.add("SELECT * FROM near EXCEPT SELECT * FROM visited", "unvisited")
    plan.add("SELECT * FROM batches UNION ALL SELECT * FROM unvisited", "made")
    links = "SELECT batch_id, dst, src FROM made b JOIN e ON e.dst = b.node_id"
    if cap:
        links = f"SELECT batch_id, dst, src FROM (SELECT *, row_number() OVER (PARTITION BY batch_id, dst ORDER BY ((src % 65536) * 40503 + dst) % 65536, src) r FROM ({links})) WHERE r <= {cap}"
    plan.add(links, "e1")
    plan.add("SELECT DISTINCT batch_id, src AS node_id FROM e1 EXCEPT SELECT batch_id, node_id FROM made", "far")
    body = """SELECT batch_id, 2 AS layer, node_id, 'target' AS role FROM batches
UNION ALL SELECT batch_id, 1, node_id, 'self' FROM batches
UNION ALL SELECT batch_id, 1, node_id, 'unvisited' FROM unvisited
UNION ALL SELECT batch_id, 1, node_id, 'visited' FROM visited
UNION ALL SELECT batch_id, 0, node_id, 'self' FROM made
UNION ALL SELECT batch_id, 0, node_id, 'unvisited' FROM far"""
    return plan.select(body) if select else plan


def _batched_sql(h_of) -> str:
    plan = Plan()
    h = h_of(plan, plan.features(WIDTH))
    plan.parts.append(BATCHES)
    return plan.select(f"SELECT b.batch_id, h.node_id, CAST(h.j AS INTEGER) AS ch, {fixed('h.x')} AS v FROM batches b JOIN {h} h ON h.node_id = b.node_id")


def _capped_sql() -> str:
    plan = _support_sql(cap=4, select=False)
    f = plan.features(WIDTH)
    need = "SELECT batch_id, node_id FROM made UNION SELECT batch_id, node_id FROM far"
    plan.add(need, "need")
    h0 = plan.add(f"SELECT n.batch_id, n.node_id, f.j, f.x FROM need n JOIN {f} f ON f.node_id = n.node_id")

    def layer(index: int, made: str, links: str, h: str, f_in: int) -> str:
        w0, w1 = plan.weights(index, 0, f_in, HIDDEN), plan.weights(index, 1, f_in, HIDDEN)
        own = plan.add(f"SELECT h.batch_id, h.node_id, w.o AS j, sum(h.x * CAST(w.w AS DOUBLE)) AS x FROM {made} m JOIN {h} h ON h.batch_id = m.batch_id AND h.node_id = m.node_id JOIN {w0} w ON w.j = h.j GROUP BY 1, 2, 3")
        mean = plan.add(f"SELECT l.batch_id, l.dst AS node_id, h.j, avg(h.x) AS x FROM {links} l JOIN {h} h ON h.batch_id = l.batch_id AND h.node_id = l.src GROUP BY 1, 2, 3")
        near = plan.add(f"SELECT h.batch_id, h.node_id, w.o AS j, sum(h.x * CAST(w.w AS DOUBLE)) AS x FROM {mean} h JOIN {w1} w ON w.j = h.j GROUP BY 1, 2, 3")
        full = plan.add(f"SELECT o.batch_id, o.node_id, o.j, coalesce(n.x, 0) AS x FROM {own} o LEFT JOIN {near} n ON n.batch_id = o.batch_id AND n.node_id = o.node_id AND n.j = o.j")
        return plan.add(f"SELECT batch_id, node_id, j, greatest(x, 0) AS x FROM {own} UNION ALL SELECT batch_id, node_id, j + {HIDDEN}, greatest(x, 0) FROM {full}")

    h1 = layer(1, "made", "e1", h0, WIDTH)
    h2 = layer(2, "batches", "e2", h1, 2 * HIDDEN)
    return plan.select(f"SELECT batch_id, node_id, CAST(j AS INTEGER) AS ch, {fixed('x')} AS v FROM {h2}")


def attention_rows(plan: Plan) -> str:
    f = plan.features(WIDTH)
    heads = []
    for i in range(2):
        z = plan.product(f, plan.weights(1, i, WIDTH, 2))
        a, b = plan.weights(2, i, 2, 1), plan.weights(3, i, 2, 1)
        d = plan.add(f"SELECT node_id, sum(x * CAST(w AS DOUBLE)) AS s FROM {z} z JOIN {a} a ON a.j = z.j GROUP BY 1")
        s = plan.add(f"SELECT node_id, sum(x * CAST(w AS DOUBLE)) AS s FROM {z} z JOIN {b} b ON b.j = z.j GROUP BY 1")
        raw = plan.add(f"SELECT dst, src, d.s + s.s AS r FROM e JOIN {d} d ON d.node_id = e.dst JOIN {s} s ON s.node_id = e.src")
        leaky = plan.add(f"SELECT dst, src, CASE WHEN r > 0 THEN r ELSE r * 0.2::DOUBLE END AS r FROM {raw}")
        top = plan.add(f"SELECT dst, max(r) AS top FROM {leaky} GROUP BY 1")
        w = plan.add(f"SELECT l.dst, l.src, exp(r - top) AS w FROM {leaky} l JOIN {top} t ON t.dst = l.dst")
        mean = plan.add(f"SELECT w.dst AS node_id, z.j, sum(w.w * z.x) / sum(w.w) AS x FROM {w} w JOIN {z} z ON z.node_id = w.src GROUP BY 1, 2")
        heads.append((plan.add(f"SELECT z.node_id, z.j, coalesce(m.x, 0) AS x FROM {z} z LEFT JOIN {mean} m ON m.node_id = z.node_id AND m.j = z.j"), 2))
    return plan.relu(plan.concat(heads))


def _attention_sql() -> str:
    plan = Plan()
    return plan.cells(attention_rows(plan))


def _edge_sql(graph: str) -> str:
    return Plan(graph).select("SELECT dst, src FROM e")


def _one_layer(orders: range, **how) -> str:
    plan = Plan()
    return plan.cells(plan.layer(plan.features(WIDTH), 1, orders, WIDTH, HIDDEN, **how))


def _step_sql(k: int) -> str:
    plan = Plan()
    h = plan.features(WIDTH)
    for _ in range(k):
        h = plan.step(h)
    return plan.cells(h)


def _weights_sql(value: str, extra: str = "") -> str:
    plan = Plan()
    if extra:
        plan.add("SELECT dst, src FROM e UNION SELECT node_id, node_id FROM (SELECT dst AS node_id FROM e UNION SELECT src FROM e)", "g")
    g = "g" if extra else "e"
    plan.add(f"SELECT dst, count(*) AS n FROM {g} GROUP BY 1", "deg")
    return plan.select(f"SELECT g.dst, g.src, {fixed(value)} AS v FROM {g} g JOIN deg a ON a.dst = g.dst LEFT JOIN deg b ON b.dst = g.src")


def oracle_sql() -> dict[str, str]:
    forward = lambda: (lambda p: p.cells(_two(p, p.features(WIDTH))))(Plan())

    def jump() -> str:
        p = Plan()
        first = p.layer(p.features(WIDTH), 1, range(0, 2), WIDTH, HIDDEN)
        return p.cells(p.concat([(first, 2 * HIDDEN), (p.layer(first, 2, range(0, 2), 2 * HIDDEN, HIDDEN), 2 * HIDDEN)]))

    def residual() -> str:
        p = Plan()
        f = p.features(WIDTH)
        y = p.layer(f, 1, range(0, 2), WIDTH, WIDTH // 2)
        return p.cells(p.add(f"SELECT y.node_id, y.j, y.x + f.x AS x FROM {y} y JOIN {f} f ON f.node_id = y.node_id AND f.j = y.j"))

    def masked(eta):
        p = Plan()
        return p.cells(_masked(p, p.features(WIDTH), eta, False))

    self_mean = _one_layer(range(0, 2))
    return {
        **{f"edges_{g}": _edge_sql(g) for g in ("purchase", "copurchase", "chain", "supply", "event", "reply", "doc", "knn")},
        "hyperlink_edges": """SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pages""",
        "replicate_graph": Plan().select("SELECT dst + c * 1000000 AS dst, src + c * 1000000 AS src FROM e, range(3) r(c)"),
        "degree_row_mean": _weights_sql("CAST(1 AS DOUBLE) / a.n"),
        "degree_sym": _weights_sql("CAST(1 AS DOUBLE) / sqrt(a.n * coalesce(b.n, 1))"),
        "degree_self_loop": _weights_sql("CAST(1 AS DOUBLE) / a.n", "loops"),
        "propagate_1": _step_sql(1),
        "propagate_2": _step_sql(2),
        "propagate_array_layout": _step_sql(1),
        "propagate_long_layout": _step_sql(1),
        "layer_convolution": _one_layer(range(1, 2)),
        "layer_self_mean": self_mean,
        "layer_multi_order": _one_layer(range(0, 3)),
        "layer_dense": _one_layer(range(0, 1)),
        "layer_mean_combine": _one_layer(range(0, 2), combine="mean"),
        "layer_residual": residual(),
        "layer_attention": _attention_sql(),
        "multiply_first": self_mean,
        "aggregate_first": self_mean,
        "forward_two_layer": forward(),
        "forward_jumping": jump(),
        "batch_former": (lambda p: (p.parts.append(BATCHES), p.select("SELECT batch_id, node_id FROM batches"))[1])(Plan()),
        "support_two_hop": _support_sql(),
        "support_capped": _support_sql(cap=4),
        "support_with_store": _support_sql(store=True),
        "batched_two_layer": _batched_sql(_two),
        "batched_capped": _capped_sql(),
        "batched_with_store": _batched_sql(_two),
        **{f"pruned_forward_{n}x": masked(1 / n) for n in (2, 4, 8)},
        **{f"pruned_batched_{n}x": _batched_sql(lambda p, h, n=n: _masked(p, h, 1 / n, True)) for n in (2, 4, 8)},
    }
