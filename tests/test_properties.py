import numpy as np
import pytest
from pyspark.sql import functions as F

from prunegraph.functions import cost as C
from prunegraph.functions import metrics as M
from prunegraph.operators import edges as E
from prunegraph.operators import prune as P
from prunegraph.operators import train as T
from prunegraph.operators.layers import AttentionLayer, GraphLayer, Network, infer_full, presets
from prunegraph.operators.propagate import normalize, propagate
from prunegraph.operators.support import infer_batched, make_batches, support_sets
from prunegraph.plans.headline import WIDTH, base, two_layer
from prunegraph.sources.tables import node_ids


@pytest.fixture(scope="module")
def bought(spark, small):
    nodes, edges, feats = base(spark, small)
    return nodes.persist(), edges.persist(), feats.persist()


def rows_of(df, *keys):
    return {tuple(r[k] for k in keys): np.array(r["h"]) for r in df.collect()}


@pytest.mark.parametrize("cell", [("a", 0, 545, 531), ("a", 1, 211, 269), ("b", 0, 1242, 1997), ("b", 1, 360, 1002), ("c", 0, 317, 852), ("c", 3, 85, 652), ("d", 0, 1490, 8459), ("d", 2, 180, 2155)])
def test_published_cost_cells(cell):
    from prunegraph.plans.measures import PUBLISHED

    name, power, kmacs, mib = cell
    _, f, h, c, v, e = next(p for p in PUBLISHED if p[0] == name)
    assert abs(C.printed_full_kmacs(f, h, c, v, e, 0.5**power) - kmacs) < 2.5
    assert abs(C.printed_full_mib(f, h, v, e, 0.5**power) - mib) < 2.5


@pytest.mark.parametrize("name,kmacs", [("b", 3135), ("c", 17665), ("d", 7870)])
def test_published_batched_cost_is_near(name, kmacs):
    from prunegraph.plans.measures import PUBLISHED

    _, f, h, c, v, e = next(p for p in PUBLISHED if p[0] == name)
    assert abs(C.printed_batched_kmacs(f, h, c, v, e) / kmacs - 1) < 0.04


def test_rows_of_the_mean_sum_to_one(bought):
    _, edges, feats = bought
    w = normalize(edges).groupBy("dst").agg(F.sum("w").alias("w"))
    assert w.filter(F.abs(F.col("w") - 1) > 1e-9).isEmpty()
    ones = feats.select("node_id", F.array(F.lit(1.0)).alias("h"))
    assert propagate(edges, ones, 1).filter(F.abs(F.col("h")[0] - 1) > 1e-12).isEmpty()


def test_full_budget_changes_nothing(bought):
    nodes, edges, feats = bought
    net = two_layer()
    stats = P.network_grams(net, edges, feats, nodes, WIDTH, P.full_scheme(1.0, 2))
    pruned, _ = P.prune_network(net, stats, P.Scheme({2: 1.0}))
    a, b = (rows_of(infer_full(n, nodes, edges, feats, WIDTH), "node_id") for n in (net, pruned))
    assert all(np.allclose(a[k], b[k], atol=1e-5) for k in a)


def test_dead_and_double_channels_go_free():
    x = np.random.default_rng(0).standard_normal((200, 5))
    x[:, 3] = x[:, 1]
    w = np.random.default_rng(1).standard_normal((5, 3))
    w[4] = 0
    done = P.prune_layer({0: x.T @ x}, {0: w}, 3 / 5)
    assert 4 not in done.kept and done.relative_loss < 1e-8


def test_loss_by_rows_and_stochastic_twins():
    rng = np.random.default_rng(2)
    x, w = rng.standard_normal((3000, 6)), rng.standard_normal((6, 4))
    g = x.T @ x
    kept = np.array([0, 2, 5])
    folded = P.solve_weights(g, np.ones(6), w, kept)
    assert P.loss(g, w, kept, folded) == pytest.approx(((x @ w - x[:, kept] @ folded) ** 2).sum(), rel=1e-8)
    near = P.sgd_weights(x[:, kept], x @ w, w[kept], epochs=200)
    assert P.loss(g, w, kept, near) < 1.05 * P.loss(g, w, kept, folded)
    q, r = P.mask_terms({0: g}, {0: w})
    lam = np.abs(r).max() * 0.8
    f = lambda b: b @ q @ b - 2 * r @ b + lam * np.abs(b).sum()
    exact, rough = P.lasso_mask(q, r, lam), P.sgd_mask({0: x}, {0: w}, lam, epochs=200)
    assert f(exact) <= f(rough) + 1e-6 * abs(f(exact)) and f(rough) < f(exact) + 0.05 * abs(f(exact))


def test_lasso_beside_brute_force():
    from itertools import combinations

    rng = np.random.default_rng(3)
    better = 0
    for _ in range(10):
        x = rng.standard_normal((300, 6)) @ rng.standard_normal((6, 6))
        x /= x.std(axis=0)
        w = rng.standard_normal((6, 4))
        g = x.T @ x
        lost = {c: P.loss(g, w, np.array(c), P.solve_weights(g, np.ones(6), w, np.array(c))) for c in combinations(range(6), 3)}
        mine = P.prune_layer({0: g}, {0: w}, 0.5).loss
        better += mine <= np.mean(list(lost.values()))
        assert mine >= min(lost.values()) - 1e-6
    assert better >= 8


def test_batched_equals_full_on_targets(bought):
    nodes, edges, feats = bought
    net = two_layer()
    full = rows_of(infer_full(net, nodes, edges, feats, WIDTH), "node_id")
    batches = make_batches(nodes.filter(E.split_of() == "test"), 16)
    got = rows_of(infer_batched(net, batches, edges, feats, WIDTH), "node_id")
    assert len(got) == batches.count() and all(np.allclose(full[k], h) for k, h in got.items())


def test_batches_partition_targets(bought):
    nodes, _, _ = bought
    sizes = [r["count"] for r in make_batches(nodes, 64).groupBy("batch_id").count().orderBy("batch_id").collect()]
    assert sum(sizes) == nodes.count() and set(sizes[:-1]) == {64} and sizes[-1] <= 64


def test_store_of_everything_is_one_hop(bought):
    nodes, edges, feats = bought
    net = two_layer()
    kept = net.layers[0].forward(nodes, edges, feats, WIDTH).select(F.lit(1).alias("layer"), "node_id", "h")
    batches = make_batches(nodes.filter(E.split_of() == "test"), 1000)
    plain, _, _ = support_sets(batches, edges, 2)
    saved, _, _ = support_sets(batches, edges, 2, None, kept)
    assert saved.filter("layer = 1 and role = 'unvisited'").isEmpty()
    assert saved.filter("layer = 0").count() <= plain.filter("layer = 0").count()
    a, b = (rows_of(infer_batched(net, batches, edges, feats, WIDTH, store=s), "node_id") for s in (None, kept))
    assert all(np.allclose(a[k], b[k]) for k in a)


def test_test_nodes_do_not_leak(spark, bought):
    nodes, edges, feats = bought
    train = nodes.filter(E.split_of() == "train")
    other = feats.withColumn("h", F.when(E.split_of() == "test", F.transform("h", lambda x: x + 9.0)).otherwise(F.col("h")))
    more = edges.unionByName(spark.createDataFrame([(4 * 10**6 + 3, 4)], "dst long, src long"))
    a, b = (P.branch_grams(e, f, train, WIDTH, [1])[1] for e, f in ((edges, feats), (more, other)))
    assert np.allclose(a, b)


def test_scheme_masks(bought):
    nodes, edges, feats = bought
    net = two_layer()
    scheme = P.batched_scheme(0.75)
    stats = P.network_grams(net, edges, feats, nodes.filter(E.split_of() == "train"), WIDTH, scheme)
    pruned, report = P.prune_network(net, stats, scheme)
    first, second = pruned.layers
    assert len(first.kept_branch[1]) == 6 and 0 not in first.kept_branch
    assert {len(w) for w in second.weights.values()} == {6} and first.f_out == 6
    assert len(infer_full(pruned, nodes, edges, feats, WIDTH).first()["h"]) == second.f_out
    assert sum(c["macs"] for c in C.measured_full(pruned, 100, 500, WIDTH)) < sum(c["macs"] for c in C.measured_full(net, 100, 500, WIDTH))
    assert {r["layer"] for r in report} == {1, 2}


def test_replicas_predict_alike(bought):
    nodes, edges, feats = bought
    more, links = E.replicate(feats, edges, 2, 10**7)
    got = rows_of(infer_full(two_layer(), more.select("node_id"), links, more, WIDTH), "node_id")
    assert len(got) == 2 * nodes.count()
    assert all(np.allclose(h, got[(k[0] + 10**7,)]) for k, h in got.items() if k[0] < 10**7)


def test_micro_f1(spark):
    one = spark.createDataFrame([(0, 0), (1, 1), (2, 1), (1, 2)], "label int, pred int")
    assert M.micro_f1(one).first()["micro_f1"] == 0.5
    many = spark.createDataFrame([([True, False], [True, True]), ([True, True], [False, True])], "label array<boolean>, pred array<boolean>")
    assert M.micro_f1(many, multilabel=True).first()["micro_f1"] == pytest.approx(2 / 3)


@pytest.mark.parametrize("multilabel", [False, True])
def test_gradients_by_differences(multilabel):
    rng = np.random.default_rng(4)
    n = 12
    dst, src = rng.integers(0, n, 40), rng.integers(0, n, 40)
    y = rng.integers(0, 2, (n, 3)).astype(float) if multilabel else rng.integers(0, 3, n)
    s = T.Sample(rng.standard_normal((n, 4)), y, dst, src, np.ones(n))
    net = T.build(4, [3, 3], 3, 0, 2)
    mean = T.Mean(n, dst, src)
    _, grads = T.gradients(net, s, mean, multilabel)
    params = T.parameters(net)
    for p, g in zip(params, grads):
        at = tuple(rng.integers(0, d) for d in p.shape)
        old = p[at]
        values = []
        for step in (1e-6, -1e-6):
            p[at] = old + step
            values.append(T.gradients(net, s, mean, multilabel)[0])
        p[at] = old
        assert (values[0] - values[1]) / 2e-6 == pytest.approx(g[at], rel=1e-3, abs=1e-7)


def test_neighbours_beat_own_attributes(spark, small):
    from prunegraph.plans.training import Task

    task = Task(spark, "/root/testdata/sf0.01")
    samples = task.samples()
    score = {k: T.train(T.build(task.width, [16, 16], task.classes, 0, k), samples, 40, decay=1e-3) for k in (0, 1)}
    f1 = {k: task.accuracy(infer_full(n, task.nodes, task.edges, task.feats, task.width, persist=True)) for k, n in score.items()}
    task.close()
    assert f1[1] > f1[0] + 0.05


def test_odd_graphs(spark):
    nodes = spark.createDataFrame([(1,), (2,)], "node_id long")
    none = spark.createDataFrame([], "dst long, src long")
    feats = spark.createDataFrame([(1, [1.0, -2.0]), (2, [0.0, 3.0])], "node_id long, h array<double>")
    net = presets.self_and_mean([2, 2])
    assert infer_full(net, nodes, none, feats, 2).count() == 2
    loop = spark.createDataFrame([(1, 1)], "dst long, src long")
    assert rows_of(propagate(loop, feats, 2, nodes), "node_id")[(2,)].tolist() == [0, 0]
    att = AttentionLayer([(np.eye(2), np.ones(2), np.ones(2))])
    assert att.forward(nodes, loop, feats, 2).count() == 2
    assert P.budget(0.01, 8) == 1
    with pytest.raises(ValueError):
        P.gram(feats, P.MOST_CHANNELS + 1)


def test_stream_matches_batch(spark, small, tmp_path):
    from prunegraph.operators.store import FeatureStore
    from prunegraph.streaming.scorer import StreamScorer

    nodes, edges, feats = base(spark, small)
    when = nodes.withColumn("ts", F.timestamp_seconds(F.col("node_id") * 1800))
    for i, part in enumerate(when.randomSplit([1.0, 1.0], seed=1)):
        part.coalesce(1).write.parquet(f"{tmp_path}/in/p{i}")
    stream = spark.readStream.schema("node_id long, ts timestamp").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")
    job = StreamScorer(two_layer(), WIDTH, edges, feats, FeatureStore(spark, f"{tmp_path}/store"), sink=f"{tmp_path}/out")
    job.run(stream, f"{tmp_path}/check")
    got = rows_of(spark.read.parquet(f"{tmp_path}/out"), "node_id")
    want = rows_of(infer_full(two_layer(), nodes, edges, feats, WIDTH), "node_id")
    assert len(got) == len(want) and all(np.allclose(got[k], want[k]) for k in got)
    assert job.daily(spark).count() >= 1


def test_plans(spark, small, bought):
    _, edges, feats = bought
    text = propagate(E.purchase(spark, small), feats, WIDTH)._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in text
    assert "Python" not in text


# ------------------------------------------------------------------ pruning variants


def _rows(spark, x):
    return spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "node_id long, h array<double>")


def test_descent_over_distributed_rows(spark):
    """Mini-batches on the table reach what the exact solvers reach."""
    rng = np.random.default_rng(0)
    x = rng.standard_normal((300, 6))
    x[:, 3:] *= 0.05  # three channels hardly matter
    w = rng.standard_normal((6, 4))
    rows = P.RowBatches.write({0: _rows(spark, x)}, 6, 300, batch=150)
    path = P.descend_mask(rows, {0: w}, 3)
    kept = P.clip_mask(path.beta, 3)
    assert path.stopped in ("budget", "over-penalised", "epochs") and kept.tolist() == [0, 1, 2]
    found = P.descend_weights(rows, {0: w}, np.ones(6), kept, epochs=6)[0]
    exact = P.solve_weights(x.T @ x, np.ones(6), w, kept)
    g = x.T @ x
    assert P.loss(g, w, kept, found) <= 1.05 * P.loss(g, w, kept, exact) + 1e-2 * np.einsum("jo,jk,ko->", w, g, w)


def test_schedule_stops_when_all_masks_fall():
    q, r = np.eye(4) * 10, np.full(4, 10.0)
    path = P.solve_mask(q, r, 1, P.PenaltySchedule(falls=1))
    assert path.stopped == "over-penalised" and path.epochs <= 3


def test_mask_folds_into_weights():
    rng = np.random.default_rng(1)
    x, w = rng.standard_normal((50, 5)), rng.standard_normal((5, 3))
    done = P.prune_layer({0: x.T @ x}, {0: w}, 0.6)
    beta, kept = done.path.beta, done.kept
    hat = np.linalg.lstsq(x[:, kept] * beta[kept], x @ w, rcond=None)[0]
    assert np.allclose(done.weights[0], P.fold_mask(beta, hat, kept), atol=1e-5)


def test_averaged_branches_are_pruned_together(spark):
    """The Gram of branches side by side gives the least-squares answer."""
    rng = np.random.default_rng(2)
    x = [rng.standard_normal((80, 4)) for _ in range(2)]
    w = [rng.standard_normal((4, 3)) for _ in range(2)]
    wide = P.cross_gram([_rows(spark, v) for v in x], 4)
    both = np.concatenate(x, 1)
    assert np.allclose(wide, both.T @ both)
    done = P.prune_averaged(wide, w, 0.5)
    at = np.concatenate([done.kept, done.kept + 4])
    want = np.linalg.lstsq(both[:, at], both @ np.concatenate(w), rcond=None)[0]
    assert np.allclose(np.concatenate([done.weights[0], done.weights[1]]), want, atol=1e-5)


def test_attention_heads_are_pruned(spark, bought):
    """With all channels kept a pruned attention layer is the layer itself."""
    from prunegraph.plans.headline import _attention

    nodes, edges, feats = bought
    layer = _attention()
    frames = layer.mixed_inputs(nodes, edges, feats, WIDTH)
    whole, _ = P.prune_heads(frames, feats, layer, WIDTH, 1.0)
    a = rows_of(layer.forward(nodes, edges, feats, WIDTH), "node_id")
    b = rows_of(whole.forward(nodes, edges, feats, WIDTH), "node_id")
    assert all(np.allclose(a[k], b[k], atol=1e-4) for k in a)
    half, done = P.prune_heads(frames, feats, layer, WIDTH, 0.5)
    assert len(done.kept) == WIDTH // 2 and 0 <= done.relative_loss < 1 and half.forward(nodes, edges, feats, WIDTH).count() == nodes.count()


def test_jumping_gradient():
    """The gradient of a network that reads every layer, against differences."""
    rng = np.random.default_rng(3)
    net = T.build(3, [2, 2], 2, seed=1)
    net.readout, net.head = "concat_all", rng.standard_normal((8, 2))
    dst, src = np.array([0, 0, 1, 2, 3]), np.array([1, 2, 0, 3, 1])
    sample = T.Sample(rng.standard_normal((4, 3)), np.array([0, 1, 1, 0]), dst, src, np.ones(4))
    mean = T.Mean(4, dst, src)
    _, grads = T.gradients(net, sample, mean)
    for value, g in zip(T.parameters(net), grads):
        at = tuple(0 for _ in value.shape)
        old = value[at]
        value[at] = old + 1e-5
        up = T.gradients(net, sample, mean)[0]
        value[at] = old - 1e-5
        down = T.gradients(net, sample, mean)[0]
        value[at] = old
        assert abs((up - down) / 2e-5 - g[at]) < 1e-5


def test_attention_reads_edges_once_and_broadcasts_no_nodes(spark):
    """Heads of unlike widths equal the plain formula; node tables are never sent to the driver."""
    rng = np.random.default_rng(5)
    x = rng.standard_normal((6, 3))
    pairs = [(0, 1), (0, 2), (1, 0), (2, 3), (2, 4), (2, 0), (4, 4)]
    heads = [(rng.standard_normal((3, f)), rng.standard_normal(f), rng.standard_normal(f)) for f in (2, 1, 3)]
    feats = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "node_id long, h array<double>")
    edges = spark.createDataFrame(pairs, "dst long, src long")
    found = AttentionLayer(heads).forward(feats.select("node_id"), edges, feats, 3)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" not in plan and plan.count("SortMergeJoin") == 3
    expected = {}
    for v in range(len(x)):
        out, near = [], [s for d, s in pairs if d == v]
        for w, a, b in heads:
            z = x @ w
            e = np.array([z[v] @ a + z[s] @ b for s in near])
            p = np.exp(np.where(e > 0, e, 0.2 * e))
            out.append((p / p.sum()) @ z[near] if near else np.zeros(w.shape[1]))
        expected[(v,)] = np.maximum(np.concatenate(out), 0)
    got = rows_of(found, "node_id")
    assert got.keys() == expected.keys() and all(np.allclose(got[k], expected[k]) for k in got)


def _small_graph(spark):
    x = np.arange(1.0, 6.0)
    pairs = [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4), (4, 0)]
    net = Network([GraphLayer({0: np.eye(1), 1: np.eye(1)}), GraphLayer({0: np.eye(2), 1: np.eye(2)})])
    feats = spark.createDataFrame([(i, [float(v)]) for i, v in enumerate(x)], "node_id long, h array<double>")
    return x, {d: [s for e, s in pairs if e == d] for d in range(5)}, net, feats, spark.createDataFrame(pairs, "dst long, src long")


def test_batches_share_each_nodes_output(spark, monkeypatch):
    """A node that many batches need is computed once a layer."""
    from prunegraph.operators import support

    _, _, net, feats, edges = _small_graph(spark)
    sizes, kept = [], support.written
    monkeypatch.setattr(support, "written", lambda df, name="step": (sizes.append((name, df.count())), kept(df, name))[1])
    batches = spark.createDataFrame([(b, n) for b in range(4) for n in (0, 1, 2)], "batch_id int, node_id long")
    found = infer_batched(net, batches, edges, feats, 1)
    assert found.count() == 12 and len({tuple(r["h"]) for r in found.filter("node_id = 0").collect()}) == 1
    assert max(n for name, n in sizes if name in ("features", "links")) <= 6


def test_stored_features_depend_on_the_batch(spark):
    """Neighbours in the own batch are computed, others are read, also where the store is stale."""
    x, near, net, feats, edges = _small_graph(spark)
    kept = spark.createDataFrame([(1, i, [100.0 + i, 200.0 + i]) for i in range(5)], "layer int, node_id long, h array<double>")
    batches = {0: [0, 1], 1: [2, 3], 2: [0, 4]}
    rows = spark.createDataFrame([(b, n) for b, ns in batches.items() for n in ns], "batch_id int, node_id long")
    first = lambda v: np.array([x[v], np.mean([x[s] for s in near[v]])])
    expected = {}
    for b, own in batches.items():
        for v in own:
            there = [first(s) if s in own else np.array([100.0 + s, 200.0 + s]) for s in near[v]]
            expected[(b, v)] = np.concatenate([first(v), np.mean(there, axis=0)])
    got = rows_of(infer_batched(net, rows, edges, feats, 1, store=kept), "batch_id", "node_id")
    assert got.keys() == expected.keys() and all(np.allclose(got[k], expected[k]) for k in got)


def test_student_broadcasts_no_nodes(spark):
    from prunegraph.operators import baselines as B
    from prunegraph.plans.headline import _attention

    feats = spark.createDataFrame([(i, [1.0] * 8) for i in range(4)], "node_id long, h array<double>")
    edges = spark.createDataFrame([(0, 1), (1, 2)], "dst long, src long")
    found = B.student(edges, feats, 8, feats.select("node_id"), _attention(), np.ones((4, 2)))
    assert "BroadcastHashJoin" not in found._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("stored", [False, True])
def test_counts_equal_support_sets(bought, stored):
    from prunegraph.operators.support import expansion, neighbour_lists, read_counts
    from prunegraph.plans.training import counts_of

    nodes, edges, _ = bought
    batches = make_batches(nodes.filter(E.split_of() == "test"), 16)
    store = nodes.filter("node_id % 3 = 0").select(F.lit(1).alias("layer"), "node_id") if stored else None
    support, used, _ = support_sets(batches, edges, 2, {2: 4}, store)
    _, links, given, made = expansion(batches, edges, 2, {2: 4}, store, lowest=2)
    lists = neighbour_lists(edges, 4)
    found = counts_of(links, given, made, lists)
    each = lambda layer: support.filter(F.col("layer") == layer).groupBy("batch_id").agg(F.countDistinct("node_id").alias("n"))
    assert found["links_1"] == used[1].count() and found["links_2"] == used[2].count()
    assert found["made_1"] == support.filter("layer = 1 and role <> 'visited'").count()
    assert found["read"] == support.filter("layer = 0").count()
    assert found["most_read"] == each(0).agg(F.max("n")).first()[0] and found["most_held"] == each(1).agg(F.max("n")).first()[0]
    wide = make_batches(nodes.filter(E.split_of() == "test"), 64)
    joined, _, _ = support_sets(wide, edges, 2, {2: 4}, store)
    want = {r["batch_id"]: r["n"] for r in joined.filter("layer = 0").groupBy("batch_id").agg(F.countDistinct("node_id").alias("n")).collect()}
    if not stored:
        assert {r["batch_id"]: r["read"] for r in read_counts(made[1], lists, (1, 4)).filter("times = 4").collect()} == want


def test_memory_limit_counts_all_sizes_in_one_pass(spark, small, monkeypatch):
    from prunegraph.operators import support as S
    from prunegraph.plans.training import memory_limit

    expanded, once = [], S.expand
    monkeypatch.setattr(S, "expand", lambda *a: (expanded.append(1), once(*a))[1])
    monkeypatch.setattr(S, "COUNTED_AT_ONCE", 500)
    rows = {r["size"]: r for r in memory_limit(spark, small, 10_000).collect()}
    # only the hop to the targets' neighbours is written, once for all sizes
    assert len(expanded) == 1
    nodes, edges, _ = base(spark, small)
    for size in (16, 64, 256):
        support, _, _ = support_sets(make_batches(nodes.filter(E.split_of() == "test"), size), edges, 2, {2: 32})
        read = [r["bytes"] for r in C.input_bytes(support, WIDTH).collect()]
        assert rows[size]["batches"] == len(read) and rows[size]["most_bytes"] == max(read) and rows[size]["fitting"] == sum(b <= 10_000 for b in read)


def test_read_counts_with_far_ids(spark):
    from prunegraph.operators.support import neighbour_lists, read_counts

    edges = spark.createDataFrame([(1, -(1 << 62)), (1, (1 << 62) + 5), (2, 3), (2, (1 << 31) + 3), (3, 1), (3, (1 << 31))], "dst long, src long")
    lists = neighbour_lists(edges)
    assert {r["node_id"]: r["near"] is None for r in lists.collect()} == {1: True, 2: True, 3: False}
    made = spark.createDataFrame([(0, 1), (0, 3), (1, 2), (1, 3), (1, 9)], "batch_id int, node_id long")
    found = {(r["times"], r["batch_id"]): (r["made"], r["links"], r["read"]) for r in read_counts(made, lists, (1, 2)).collect()}
    assert found == {(1, 0): (2, 4, 5), (1, 1): (3, 4, 6), (2, 0): (5, 8, 8)}


def test_scale_ladder_writes_no_copy_of_the_graph(spark, small, monkeypatch):
    from prunegraph.plans import training

    sizes, own = {}, training.written

    def written(df, name="step"):
        out = own(df, name)
        sizes[name] = max(sizes.get(name, 0), out.count())
        return out

    monkeypatch.setattr(training, "written", written)
    nodes, edges, _ = base(spark, small)
    rows = {r["copies"]: r["nodes"] for r in training.scale_ladder(spark, small, (1, 3)).collect()}
    assert rows == {1: nodes.count(), 3: 3 * nodes.count()}
    assert sizes == {"nodes": nodes.count(), "edges": edges.count()}


def test_blocks_give_the_means_of_the_join(spark):
    """Hubs over several blocks, sources without features, nodes without neighbours, repeated edges."""
    from prunegraph.operators.blocks import blocked
    from prunegraph.sources.shared import written

    rng = np.random.default_rng(3)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 60, (400, 2))] + [(7, i) for i in range(300)] + [(1 << 40, 5), (70, 900)]
    edges = written(spark.createDataFrame(pairs, "dst long, src long"), "edges")
    feats = spark.createDataFrame([(i, [float(x) for x in rng.standard_normal(3)]) for i in range(250)], "node_id long, h array<double>")
    nodes = spark.createDataFrame([(i,) for i in [*range(80), 1 << 40]], "node_id long")
    plain = rows_of(propagate(edges, feats, 3, nodes), "node_id")
    dealt = blocked(edges, 64)
    fast = rows_of(propagate(dealt, feats, 3, nodes), "node_id")
    assert dealt._blocks.tables()[0].count() > 5
    assert plain.keys() == fast.keys() and all(np.allclose(plain[k], fast[k]) for k in plain)


def test_full_inference_deals_edges_once(spark, small):
    """Propagations of a workload's task read dealt blocks: no plan sorts or joins the edges again."""
    from prunegraph.plans import training

    task = training.Task(spark, small)
    net = T.build(task.width, [16, 16], task.classes)
    scores = task.infer(net)
    hidden = net.layers[0].forward(task.nodes, task.edges, task.feats, task.width)
    plan = hidden._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and f"{task.edges._written_path.split('/')[-1]}" not in plan
    plain = infer_full(net, task.nodes, task.edges.select("dst", "src"), task.feats, task.width)
    a, b = rows_of(scores, "node_id"), rows_of(plain, "node_id")
    assert a.keys() == b.keys() and all(np.allclose(a[k], b[k]) for k in a)
    both = {(r["dst"], r["src"]) for r in E.inside(task.edges, task.train).collect()}
    assert both == {(r["dst"], r["src"]) for r in task.inner.collect()}
    task.close()


@pytest.mark.parametrize("stored", [False, True])
def test_networks_share_their_support(spark, bought, monkeypatch, stored):
    """Budgets differ in weights only: with the support given, nodes and links are not worked out again."""
    from prunegraph.operators import support as U
    from prunegraph.sources.shared import written

    nodes, edges, feats = bought
    edges, net = written(edges.select("dst", "src"), "edges"), two_layer()
    batches = written(make_batches(nodes.filter("node_id % 5 = 1"), 16), "batches")
    store = None
    if stored:
        first = net.layers[0].forward(nodes, edges, feats, WIDTH)
        store = written(first.filter("node_id % 5 <> 1").select(F.lit(1).alias("layer"), "node_id", "h"), "kept")
    plain = rows_of(infer_batched(net, batches, edges, feats, WIDTH, {2: 4}, store), "batch_id", "node_id")
    grown = U.expansion(batches, edges, 2, {2: 4}, store, lowest=2) if stored else None
    support = U.shared_support(1, grown[3][1], edges, {2: 4}, 2) if stored else U.shared_support(2, batches, edges, {2: 4})
    names = []
    monkeypatch.setattr(U, "written", lambda df, name="step": names.append(name) or written(df, name))
    for _ in range(2):
        again = rows_of(infer_batched(net, batches, edges, feats, WIDTH, {2: 4}, store, grown, support), "batch_id", "node_id")
        assert plain.keys() == again.keys() and all(np.allclose(plain[k], again[k]) for k in plain)
    assert not {"links", "asked", "others"} & set(names)


def test_wide_features_go_by_blocks(spark):
    """Also features of more channels than the wide layout takes: no plan joins the edges with them."""
    from prunegraph.operators.blocks import blocked
    from prunegraph.sources.shared import written

    rng = np.random.default_rng(5)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, 50, (400, 2))})
    edges = written(spark.createDataFrame(pairs, "dst long, src long"), "edges")
    feats = written(spark.createDataFrame([(i, [float(x) for x in rng.standard_normal(70)]) for i in range(45)], "node_id long, h array<double>"), "features")
    nodes = spark.createDataFrame([(i,) for i in range(60)], "node_id long")
    plain = rows_of(propagate(edges, feats, 70, nodes), "node_id")
    fast = propagate(blocked(edges, 64), feats, 70, nodes)
    assert "FlatMapCoGroupsInArrow" in fast._jdf.queryExecution().executedPlan().toString()
    fast = rows_of(fast, "node_id")
    assert plain.keys() == fast.keys() and all(np.allclose(plain[k], fast[k]) for k in plain)


def test_attention_by_blocks_is_that_of_the_join(spark):
    """Hubs over several blocks, sources without features, nodes without neighbours."""
    from prunegraph.operators.blocks import blocked
    from prunegraph.sources.shared import written

    rng = np.random.default_rng(6)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, 60, (400, 2))} | {(7, i) for i in range(300)} | {(70, 900)})
    edges = written(spark.createDataFrame(pairs, "dst long, src long"), "edges")
    feats = spark.createDataFrame([(i, [3 * float(x) for x in rng.standard_normal(5)]) for i in range(250)], "node_id long, h array<double>")
    nodes = spark.createDataFrame([(i,) for i in range(80)], "node_id long")
    layer = AttentionLayer([(rng.standard_normal((5, n)), rng.standard_normal(n), rng.standard_normal(n)) for n in (3, 2)])
    plain = rows_of(layer.forward(nodes, edges, feats, 5), "node_id")
    fast = layer.forward(nodes, blocked(edges, 64), feats, 5)
    plan = fast._jdf.queryExecution().executedPlan().toString()
    assert edges._written_path.split("/")[-1] not in plan
    fast = rows_of(fast, "node_id")
    assert plain.keys() == fast.keys() and all(np.allclose(plain[k], fast[k]) for k in plain)


@pytest.mark.parametrize("rounds", [1, 2, 3])
def test_pagerank_writes_no_row_a_pair(spark, monkeypatch, rounds):
    """The last step is summed and ranked where a group of seeds is, some seeds at a time."""
    from prunegraph.operators import baselines as B
    from prunegraph.operators.blocks import blocked
    from prunegraph.sources.shared import written

    monkeypatch.setattr(B, "PUSHED_AT_ONCE", 16)
    monkeypatch.setattr(B, "PAIRS_AT_ONCE", 40)
    rng = np.random.default_rng(7)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, 40, (250, 2))} | {(3, i) for i in range(40)})
    edges = written(spark.createDataFrame(pairs, "dst long, src long"), "edges")
    # 90 has no edges and keeps its own share
    seeds = spark.createDataFrame([(i,) for i in [*range(0, 40, 3), 90]], "node_id long")
    found = lambda e: {(r["seed"], r["node_id"]): r["mass"] for r in B.personalised_pagerank(e, seeds, rounds=rounds, top=5).collect()}
    plain, fast = found(edges), found(blocked(edges))
    assert plain.keys() == fast.keys() and all(abs(plain[k] - fast[k]) < 1e-12 for k in plain)


def test_batched_budgets_read_links_dealt_once(spark, small, monkeypatch):
    """Every budget propagates over the same blocks, and labels read the written purchases."""
    from prunegraph.functions import attributes as A
    from prunegraph.operators import blocks as K
    from prunegraph.plans import training

    monkeypatch.setattr(training, "ROUNDS", 2)
    wanted = {(r["node_id"], r["label"]) for r in A.part_region(spark, small).collect()}
    dealt, real = [], K.written
    monkeypatch.setattr(K, "written", lambda df, name="step": dealt.append(name) or real(df, name))
    given, region = [], A.part_region
    monkeypatch.setattr(A, "part_region", lambda *a: given.append(len(a)) or region(*a))
    task = training.Task(spark, small)
    assert given == [3] and {(r["node_id"], r["label"]) for r in task.labels.collect()} == wanted
    task.close()
    rows = training.batched_inference(spark, small, etas=(0.5,)).collect()
    assert len(rows) == 4
    # whole graph, training graph, two layers of one support and one of the other
    assert 2 < dealt.count("blocks") <= 5
