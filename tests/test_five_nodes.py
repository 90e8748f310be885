"""The hand-worked graph: edges 0-1, 0-2, 0-3, 3-4."""

import numpy as np
import pytest

from prunegraph.functions import cost as C
from prunegraph.operators import prune as P
from prunegraph.operators.layers import GraphLayer
from prunegraph.operators.propagate import propagate, propagate_k
from prunegraph.operators.support import support_sets

H = np.array([[1, 0, 2], [0, 2, 0], [2, 0, 0], [4, 2, 2], [0, 0, 4]], float)
PAIRS = [(0, 1), (0, 2), (0, 3), (3, 4)]
W0 = np.array([[1, 0], [0, 1], [1, 0]], float)
W1 = np.array([[1, 0], [0, 0], [0, 2]], float)


@pytest.fixture(scope="module")
def graph(spark):
    nodes = spark.createDataFrame([(i,) for i in range(5)], "node_id long")
    edges = spark.createDataFrame([p for a, b in PAIRS for p in ((a, b), (b, a))], "dst long, src long")
    feats = spark.createDataFrame([(i, H[i].tolist()) for i in range(5)], "node_id long, h array<double>")
    return nodes, edges, feats


def matrix(df):
    return np.array([r["h"] for r in sorted(df.collect(), key=lambda r: r["node_id"])])


def dense():
    a = np.zeros((5, 5))
    for x, y in PAIRS:
        a[x, y] = a[y, x] = 1
    return a / a.sum(axis=1, keepdims=True)


@pytest.mark.parametrize("layout", ["wide", "array", "long"])
def test_layouts_agree_with_dense(graph, layout):
    nodes, edges, feats = graph
    assert np.allclose(matrix(propagate(edges, feats, 3, nodes, layout=layout)), dense() @ H)


def test_two_steps(graph):
    nodes, edges, feats = graph
    got = matrix(propagate_k(edges, feats, 2, 3, nodes)[2])
    assert np.allclose(got, dense() @ dense() @ H)
    assert np.allclose(got[0], [5 / 6, 0, 7 / 3])


@pytest.mark.parametrize("order", ["agg_first", "mul_first", "auto"])
def test_layer_by_hand(graph, order):
    nodes, edges, feats = graph
    got = matrix(GraphLayer({0: W0, 1: W1}, order=order).forward(nodes, edges, feats, 3))
    want = [(3, 0, 2, 4 / 3), (0, 2, 1, 4), (2, 0, 1, 4), (6, 2, 0.5, 6), (4, 0, 4, 4)]
    assert np.allclose(got, want)


def test_grams_and_mask_terms(graph):
    nodes, edges, feats = graph
    g = {k: P.gram(f, 3) for k, f in enumerate(propagate_k(edges, feats, 1, 3, nodes))}
    assert np.allclose(g[0], [[21, 8, 10], [8, 8, 4], [10, 4, 24]])
    q, r = P.mask_terms(g, {0: W0, 1: W1})
    assert np.allclose(q, [[173 / 4, 0, 10], [0, 8, 0], [10, 0, 988 / 9]])
    assert np.allclose(r, [213 / 4, 8, 1078 / 9])
    assert np.allclose(P.lasso_mask(q, r, 0.0), 1, atol=1e-6)
    for lam, want in ((5, (0.946332, 0.6875, 0.982116)), (10, (0.892663, 0.375, 0.964231)), (20, (0.785327, 0, 0.928462)), (40, (0.570653, 0, 0.856924))):
        assert np.allclose(P.lasso_mask(q, r, lam), want, atol=2e-6)


def test_refit_drops_channel_one(graph):
    nodes, edges, feats = graph
    g = {k: P.gram(f, 3) for k, f in enumerate(propagate_k(edges, feats, 1, 3, nodes))}
    for drop, want in ((0, 11.972525), (1, 500 / 101), (2, 35.711972)):
        kept = np.array([j for j in range(3) if j != drop])
        lost = sum(P.loss(g[k], w, kept, P.solve_weights(g[k], np.ones(3), w, kept, 0.0)) for k, w in ((0, W0), (1, W1)))
        assert lost == pytest.approx(want, rel=1e-5)
    done = P.prune_layer(g, {0: W0, 1: W1}, 2 / 3)
    assert list(done.kept) == [0, 2]


def test_rescaling_fools_weight_norm_only(graph):
    nodes, edges, feats = graph
    frames = [matrix(f) for f in propagate_k(edges, feats, 1, 3, nodes)]
    scale = np.array([1, 0.1, 1])
    g = {k: (x * scale).T @ (x * scale) for k, x in enumerate(frames)}
    w = {0: W0 / scale[:, None], 1: W1 / scale[:, None]}
    assert list(P.prune_layer(g, w, 2 / 3).kept) == [0, 2]
    assert 1 in P.select_weight_norm(w, 2)


def test_support_and_store(spark, graph):
    _, edges, _ = graph
    target = spark.createDataFrame([(0, 4)], "batch_id int, node_id long")
    store = spark.createDataFrame([(1, 3)], "layer int, node_id long")
    made = lambda rows, layer, bad=(): {r["node_id"] for r in rows.collect() if r["layer"] == layer and r["role"] not in bad}
    rows, _, _ = support_sets(target, edges, 2)
    assert made(rows, 1) == {3, 4} and made(rows, 0) == {0, 3, 4}
    rows, _, _ = support_sets(target, edges, 2, None, store)
    assert made(rows, 1, ("visited",)) == {4} and made(rows, 0) == {3, 4}


def test_cost_by_hand():
    dims = [(3, {0: 2, 1: 2})]
    assert C.full_macs(dims, 8 / 5, "agg_first") == pytest.approx(16.8)
    assert C.full_macs(dims, 8 / 5) == pytest.approx(15.2)
