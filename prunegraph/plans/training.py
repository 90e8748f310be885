"""Experiments that train, prune and re-train: accuracy, cost and time by budget."""

from __future__ import annotations

import datetime
import time
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prunegraph.functions import attributes as A
from prunegraph.functions import cost as C
from prunegraph.functions import metrics as M
from prunegraph.operators import baselines as B
from prunegraph.operators import edges as E
from prunegraph.operators import prune as P
from prunegraph.operators import train as T
from prunegraph.operators.blocks import blocked
from prunegraph.operators.layers import AttentionLayer, Network, dense_product, infer_full, predictions
from prunegraph.operators.store import FeatureStore, adaptive_share, choose
from prunegraph.operators.support import expansion, infer_batched, make_batches, neighbour_lists, read_counts, shared_support, support_sets
from prunegraph.sources.shared import forgotten, removed, shared_folder, written
from prunegraph.sources.tables import read
from prunegraph.streaming.scorer import StreamScorer

HIDDEN = 16
ROUNDS = 60
ETAS = (0.5, 0.25, 0.125)


def token_graph(spark: SparkSession, folder: str):
    """Documents that share rare words; label: the quality mark."""
    docs = read(spark, folder, "documents")
    feats = A.token_features(docs).select("node_id", "h")
    labels = read(spark, folder, "labels").filter("quality is not null").select(F.col("doc_id").cast("long").alias("node_id"), F.col("quality").cast("int").alias("label"))
    return feats, 64, E.rare_tokens(spark, folder), labels, 2


def part_graph(build, orders: bool = False, customers: bool = True):
    """A graph over parts; label: the region that buys a part most."""

    def make(spark: SparkSession, folder: str):
        feats, width = A.purchase_features(spark, folder)
        if not customers:
            feats = feats.filter("node_id % 4 = 1")
        if orders:
            none = read(spark, folder, "orders").select((F.col("o_orderkey") * 4 + 2).alias("node_id"), F.array_repeat(F.lit(0.0), width).alias("h"))
            feats = feats.unionByName(none)
        # labels come from purchases: those written as this graph, if it is theirs
        labels = (lambda edges: A.part_region(spark, folder, edges)) if build is E.purchase else A.part_region(spark, folder)
        return feats, width, build(spark, folder), labels, 5

    return make


GRAPHS = {
    "purchase": part_graph(E.purchase),
    "copurchase": part_graph(E.copurchase, customers=False),
    "chain": part_graph(E.chain, orders=True),
    "doc": token_graph,
}


class Task:
    """A graph with its label, attributes standardised on training nodes; tables written once."""

    def __init__(self, spark: SparkSession, folder: str, multilabel: bool = False, train: int = 60, val: int = 75, graph: str = "purchase"):
        raw, self.width, edges, labels, self.classes = GRAPHS[graph](spark, folder)
        self.spark, self.multilabel = spark, multilabel
        raw = written(raw, "attributes")
        self.nodes = raw.select("node_id")
        self.edges = blocked(written(edges.select("dst", "src"), "edges"))
        split = E.split_of(train=train, val=val)
        self.train = self.nodes.filter(split == "train")
        self.test = self.nodes.filter(split == "test")
        self.feats = written(A.standardize(raw, self.width, where=split == "train")[0], "features")
        removed(raw)
        self.nodes = self.feats.select("node_id")
        self.train, self.test = self.nodes.filter(split == "train"), self.nodes.filter(split == "test")
        # the graph between training nodes; most other edges go before the joins with these
        ends = [E.split_of(c, train, val) == "train" for c in ("dst", "src")]
        self.inner = blocked(written(E.inside(self.edges.filter(ends[0] & ends[1]), self.train), "inner-edges"))
        if multilabel:
            rows = A.customer_types_multi(spark, folder)
            labels = rows.groupBy("node_id").agg(F.sort_array(F.collect_list(F.struct("p_type", "label"))).alias("c")).select("node_id", F.transform("c", lambda x: x["label"] == 1).alias("label"))
            self.classes = 6
        self.labels = written(labels(self.edges) if callable(labels) else labels, "labels")
        self.n_nodes, self.n_edges = self.nodes.count(), self.edges.count()

    def samples(self, seed: int = 0, samples: int = 3, roots: int = 700):
        return T.sample_subgraphs(self.train, self.inner, self.feats, self.labels, samples, roots, 2, seed, self.classes if self.multilabel else None, induced=True)

    def reference(self, samples, k_min=0, k_max=1, hidden=HIDDEN, seed=0):
        net = T.build(self.width, [hidden, hidden], self.classes, k_min, k_max, seed=seed)
        return self.fit(net, samples)

    def fit(self, net, samples, rounds: int = ROUNDS, **how):
        return T.train(net, samples, rounds, decay=1e-3, multilabel=self.multilabel, tol=1e-3, **how)

    def accuracy(self, scores: DataFrame) -> float:
        pred = predictions(scores, self.multilabel).join(self.test, "node_id", "left_semi").join(self.labels, "node_id")
        return float(M.micro_f1(pred, multilabel=self.multilabel).first()["micro_f1"] or 0.0)

    def infer(self, net) -> DataFrame:
        return infer_full(net, self.nodes, self.edges, self.feats, self.width, persist=True)

    def kmacs(self, net) -> float:
        return sum(c["macs"] for c in C.measured_full(net, self.n_nodes, self.n_edges, self.width)) / 1000

    def close(self):
        for edges in (self.edges, self.inner):
            edges._blocks.close()
        removed(self.edges, self.inner, self.feats, self.labels)


def timed(run, times: int = 3, warm: bool = False) -> list[float]:
    """Seconds of ``times`` runs after one that warms up (none if ``warm``: the caller has run
    the same), in rising order (C9, C10)."""
    out = []
    for _ in range(times + (not warm)):
        began = time.time()
        found = run()
        found.write.format("noop").mode("overwrite").save()
        out.append(time.time() - began)
        removed(*getattr(found, "_layers", []))
        del found
        forgotten()
    return sorted(out[not warm :])


class Utilisation:
    """Busy task seconds over wall seconds times slots, of the jobs run inside."""

    def __init__(self, spark: SparkSession):
        self.sc = spark.sparkContext

    def _busy(self) -> float:
        stages = self.sc._jsc.sc().statusStore().stageList(None, False, False, self.sc._gateway.new_array(self.sc._gateway.jvm.double, 0), None)
        return sum(stages.apply(i).executorRunTime() for i in range(stages.size())) / 1000

    def __enter__(self):
        self.began, self.before = time.time(), self._busy()
        return self

    def __exit__(self, *_):
        wall = time.time() - self.began
        self.share = max(0.0, self._busy() - self.before) / max(1e-9, wall * self.sc.defaultParallelism)


def _ladder(task: Task, samples, net, scheme, etas, selector="lasso"):
    """(eta, network, pruning seconds, re-training seconds), the reference first."""
    began = time.time()
    stats = P.network_grams(net, task.inner, task.feats, task.train, task.width, scheme(0.5), induced=True)
    shared = time.time() - began
    out = [(1.0, net, 0.0, 0.0)]
    for eta in etas:
        began = time.time()
        pruned = P.prune_ladder(net, stats, scheme, (eta,), selector=selector)[eta][0]
        middle = time.time()
        again = task.fit(pruned, samples, ROUNDS // 2)
        out.append((eta, again, middle - began + shared, time.time() - middle))
    return out


def full_inference(spark: SparkSession, folder: str, etas=ETAS, multilabel: bool = False, train: int = 60, val: int = 75, graphs=("purchase", "copurchase"), seeds=(0,)) -> DataFrame:
    """Full inference by graph and budget: micro_f1, kMACs a node, bytes, nodes a second, seconds."""
    rows = []
    for graph in graphs:
        task = Task(spark, folder, multilabel, train, val, graph)
        for seed in seeds:
            samples = task.samples(seed)
            net = task.reference(samples, seed=seed)
            for eta, model, pruning, training in _ladder(task, samples, net, lambda x: P.full_scheme(x, 2), etas):
                # the run that is judged writes every layer of all nodes, as the timed one does: it warms up
                scores = task.infer(model)
                f1 = task.accuracy(scores)
                removed(*scores._layers)
                seconds = timed(lambda model=model: task.infer(model), 1, warm=True)
                cost = C.measured_full(model, task.n_nodes, task.n_edges, task.width)
                rows.append((graph, seed, float(eta), f1, task.kmacs(model), max(c["bytes"] for c in cost), task.n_nodes / seconds[0], pruning, training))
        task.close()
    runs = spark.createDataFrame(rows, "graph string, seed int, eta double, micro_f1 double, kmacs double, peak_bytes double, nodes_per_second double, prune_seconds double, retrain_seconds double")
    # the mean over repeats, and each budget against the reference (C11, C14)
    mean = runs.groupBy("graph", "eta").agg(*(F.avg(c).alias(c) for c in ("micro_f1", "kmacs", "peak_bytes", "nodes_per_second", "prune_seconds", "retrain_seconds")))
    base = mean.filter("eta = 1").select("graph", F.col("micro_f1").alias("f"), F.col("nodes_per_second").alias("t"))
    return mean.join(F.broadcast(base), "graph").withColumn("drop", F.col("f") - F.col("micro_f1")).withColumn("speedup", F.col("nodes_per_second") / F.col("t")).drop("f", "t")


def support_counts(task: Task, batches: DataFrame, cap: int, stores) -> list[dict]:
    """Per store (or None), over all batches of two layers: edges used and nodes produced by
    layer, attribute rows read in all and by the largest batch, and the most middle outputs a
    batch holds, computed or stored."""
    lists = written(neighbour_lists(task.edges, cap), "lists")
    out = []
    for store in stores:
        _, used, given, made = expansion(batches, task.edges, 2, {2: cap}, store, lowest=2)
        out.append(counts_of(used, given, made, lists))
    removed(lists)
    return out


def counts_of(used, given, made, lists: DataFrame) -> dict:
    """One entry of ``support_counts`` from an ``expansion`` down to layer 2."""
    of = read_counts(made[1], lists)
    if 1 in given:
        stored = given[1].groupBy("batch_id").agg(F.count(F.lit(1)).alias("stored"))
        of = of.join(F.broadcast(stored), "batch_id", "left")  # a row per batch
    else:
        of = of.withColumn("stored", F.lit(0))
    held = F.col("made") + F.coalesce("stored", F.lit(0))
    row = of.agg(F.sum("links").alias("links_1"), F.sum("made").alias("made_1"), F.sum("read").alias("read"), F.max("read").alias("most_read"), F.max(held).alias("most_held")).first()
    return {**{k: int(v or 0) for k, v in row.asDict().items()}, "links_2": used[2].count()}


def batched_inference(spark: SparkSession, folder: str, size: int = 512, etas=ETAS, cap: int = 32, graphs=("purchase",)) -> DataFrame:
    """Batched inference by graph and budget, with and without stored features."""
    rows = []
    for graph in graphs:
        task = Task(spark, folder, graph=graph)
        samples = task.samples()
        net = task.reference(samples)
        batches = written(make_batches(task.test, size), "batches")
        n, count = batches.count(), batches.select("batch_id").distinct().count()
        # support depends on the graph and on which nodes are stored, not on the budget: it is
        # made once, and its seconds are part of every budget's latency
        known = task.nodes.join(task.test, "node_id", "left_anti").select(F.lit(1).alias("layer"), "node_id")
        counts = support_counts(task, batches, cap, (None, known))
        ready = []
        for store in (None, known):
            began = time.time()
            grown = None if store is None else expansion(batches, task.edges, 2, {2: cap}, store, lowest=2)
            support = shared_support(2, batches, task.edges, {2: cap}) if grown is None else shared_support(1, grown[3][1], task.edges, {2: cap}, 2)
            # links are dealt once for all budgets; those nothing caps are written for it
            support = (support[0], {i: blocked(x if hasattr(x, "_written_path") else written(x, "links")) for i, x in support[1].items()})
            ready.append((grown, support, time.time() - began))
        for eta, model, *_ in _ladder(task, samples, net, lambda x: P.batched_scheme(x), etas):
            first = model.layers[0].forward(task.nodes, task.edges, task.feats, task.width)
            kept = written(first.join(task.test, "node_id", "left_anti").select(F.lit(1).alias("layer"), "node_id", "h"), "kept")
            for store, found, (grown, support, once) in zip((None, kept), counts, ready):
                began = time.time()
                f1 = task.accuracy(infer_batched(model, batches, task.edges, task.feats, task.width, {2: cap}, store, grown, support).select("node_id", "h"))
                seconds = once + time.time() - began
                macs = C.batched_from_counts(model, {1: (found["links_1"], found["made_1"]), 2: (found["links_2"], n)}, task.width, n) / 1000
                # one batch's forward path: attributes, middle outputs and stored features
                peak = 4.0 * (found["most_read"] * task.width + found["most_held"] * model.layers[0].f_out)
                rows.append((graph, float(eta), store is not None, f1, macs, float(found["most_read"] * 4 * task.width), peak, 1000 * seconds / max(1, count)))
            removed(kept)
        for _, support, _ in ready:
            for x in support[1].values():
                x._blocks.close()
        removed(batches, *(x for _, support, _ in ready for of in support for x in of.values()))
        task.close()
    return spark.createDataFrame(rows, "graph string, eta double, stored boolean, micro_f1 double, kmacs double, input_bytes double, peak_bytes double, latency_ms double")


def selector_ablation(spark: SparkSession, folder: str, fractions=(0.1, 0.3, 0.5, 0.75, 0.875), seeds=(0, 1, 2), scored=(0.5,), graph: str = "purchase") -> DataFrame:
    """Loss of layer 2, and micro-F1 after layer-wise re-training, by selector and share pruned."""
    task = Task(spark, folder, graph=graph)
    samples = task.samples()
    rows = []
    for seed in seeds:
        net = task.reference(samples, seed=seed)
        scheme = P.Scheme({2: 0.5})
        stats = P.network_grams(net, task.inner, task.feats, task.train, task.width, scheme, induced=True)
        for fraction in fractions:
            for selector in ("lasso", "weight_norm", "random"):
                done = P.prune_layer(stats[2], net.layers[1].weights, 1 - fraction, selector, seed=seed)
                zero, f1 = done.path.zero_share[-1] if done.path else None, None
                if fraction in scored and seed == seeds[0]:
                    pruned, _ = P.prune_network(net, stats, P.Scheme({2: 1 - fraction}), selector, seed=seed - 2)
                    again = task.fit(pruned, samples, ROUNDS // 2, only=2)
                    f1 = task.accuracy(task.infer(again))
                rows.append((selector, fraction, seed, done.relative_loss, zero, f1))
    task.close()
    found = spark.createDataFrame(rows, "selector string, pruned double, seed int, loss double, zero_share double, micro_f1 double")
    return found.groupBy("selector", "pruned").agg(F.avg("loss").alias("loss"), F.avg("zero_share").alias("zero_share"), F.avg("micro_f1").alias("micro_f1"))


def batch_sizes(spark: SparkSession, folder: str, sizes=(64, 128, 256, 512, 1024, 2048), cap: int = 32) -> DataFrame:
    """Latency and support of one batch by its size, median of three after a warm-up."""
    task = Task(spark, folder, graph="copurchase")
    net = task.reference(task.samples())
    rows = []
    for size in sizes:
        one = written(make_batches(task.test, size).filter("batch_id = 0"), "batch")
        seconds = timed(lambda one=one: infer_batched(net, one, task.edges, task.feats, task.width, {2: cap}))
        support, _, _ = support_sets(one, task.edges, 2, {2: cap})
        rows.append((size, one.count(), support.filter("layer = 0").select("node_id").distinct().count(), 1000 * seconds[len(seconds) // 2]))
        removed(one)
    task.close()
    return spark.createDataFrame(rows, "size int, targets long, attributes_read long, latency_ms double")


def store_fractions(spark: SparkSession, folder: str, shares=(0.0, 0.25, 0.5, 1.0), cap: int = 32) -> DataFrame:
    """Latency, drift and accuracy when features are stored before the graph grows, by stored share."""
    task = Task(spark, folder)
    net = task.reference(task.samples())
    orders = read(spark, folder, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    cut = orders.agg(F.expr("percentile_approx(unix_timestamp(cast(o_orderdate as timestamp)), 0.8)").alias("c")).first()["c"]
    old_orders = orders.filter(F.unix_timestamp(F.col("o_orderdate").cast("timestamp")) < cut)
    lines = read(spark, folder, "lineitem").select("l_orderkey", "l_partkey")
    old = E.both_ways(lines.join(old_orders, F.col("l_orderkey") == F.col("o_orderkey")).select((F.col("o_custkey") * 4).alias("a"), (F.col("l_partkey") * 4 + 1).alias("b")).distinct())
    before = written(net.layers[0].forward(task.nodes, written(old, "old-edges"), task.feats, task.width).select(F.lit(1).alias("layer"), "node_id", "h"), "stored")
    batches = written(make_batches(task.test, 512), "batches")
    exact = written(infer_batched(net, batches, task.edges, task.feats, task.width, {2: cap}).select("node_id", F.col("h").alias("exact")), "exact")
    reference = task.accuracy(exact.select("node_id", F.col("exact").alias("h")))
    lists = written(neighbour_lists(task.edges, cap), "lists")
    rows, share, latency = [], shares[0], None
    for share in shares:
        kept = choose(before, share)
        began = time.time()
        grown = expansion(batches, task.edges, 2, {2: cap}, kept, lowest=2)
        got = written(infer_batched(net, batches, task.edges, task.feats, task.width, {2: cap}, kept, grown).select("node_id", "h"), "scores")
        seconds = 1000 * (time.time() - began)
        latency = seconds if latency is None else latency
        gap = got.join(exact, "node_id").select(F.aggregate(F.zip_with("h", "exact", lambda a, b: F.abs(a - b)), F.lit(0.0), lambda s, x: s + x).alias("d")).agg(F.avg("d")).first()[0]
        found = counts_of(*grown[1:], lists)
        drop = reference - task.accuracy(got)
        # what the adaptive policy would store next, aiming at half of the latency without a store
        following = adaptive_share(share, seconds, latency / 2, drop, 0.02)
        rows.append((share, found["made_1"], found["read"], float(gap or 0.0), drop, seconds, following))
    task.close()
    return spark.createDataFrame(rows, "share double, computed_layer_1 long, attributes_read long, mean_drift double, drop double, latency_ms double, next_share double")


def architectures(spark: SparkSession, folder: str, graph: str = "purchase") -> DataFrame:
    """Trained models side by side: accuracy, cost with and without what is prepared once, speed."""
    task = Task(spark, folder, graph=graph)
    samples = task.samples()
    d = task.n_edges / task.n_nodes
    rows = []

    def add(name, net, scores=None, prepared=0.0, kmacs=None):
        run = scores or (lambda: task.infer(net))
        began = time.time()
        scored = run()
        found = written(scored.select("node_id", "h"), "scores")
        seconds = time.time() - began
        # layers and steps written on the way are read no more
        removed(*getattr(scored, "_layers", []), *getattr(scored, "_steps", []))
        del scored
        f1 = task.accuracy(found)
        removed(found)
        del found
        forgotten()
        total = task.kmacs(net) if kmacs is None else kmacs
        rows.append((name, f1, total, total - prepared / 1000, task.n_nodes / seconds))

    for name, k_min, k_max in (("mlp", 0, 0), ("convolution", 1, 1), ("self_mean", 0, 1), ("multi_order", 0, 2)):
        add(name, task.reference(samples, k_min, k_max))
    # every layer's output side by side
    jump = T.build(task.width, [HIDDEN, HIDDEN], task.classes)
    jump.readout, jump.head = "concat_all", np.random.default_rng(1).standard_normal((4 * HIDDEN, task.classes)) * 0.2
    add("jumping", task.fit(jump, samples))
    # branches over attributes propagated once: one layer whose orders each have their own product
    branches = task.fit(T.build(task.width, [HIDDEN], task.classes, 0, 2), samples)
    moved = C.preprocess_macs(d, task.width, 2)
    # printed with the propagation at full width, as it is stored
    wide = sum(w.size for w in branches.layers[0].weights.values()) + branches.head.size + moved
    ready = written(B.precomputed(task.edges, task.feats, task.width, 2, task.nodes), "prepared")
    bias = branches.layers[0].bias

    def prepared_scores():
        frame, parts = ready, sorted(branches.layers[0].weights)
        for i, k in enumerate(parts):
            frame = dense_product(frame, branches.layers[0].weights[k], column=f"h{k}", bias=bias[i * HIDDEN : (i + 1) * HIDDEN])
        h = F.transform(F.concat(*(f"h{k}" for k in parts)), lambda x: F.greatest(x, F.lit(0.0)))
        return dense_product(frame.select("node_id", h.alias("h")), branches.head, bias=branches.head_bias)

    add("precomputed_branches", branches, prepared_scores, moved, wide / 1000)
    # two hops, then one linear map
    flat = T.build(task.width, [HIDDEN], task.classes, 2, 2)
    flat.layers[0].act = None
    flat = task.fit(flat, samples)
    map_ = flat.layers[0].weights[2] @ flat.head
    shift = flat.layers[0].bias @ flat.head + flat.head_bias
    add("linear_two_hop", flat, lambda: dense_product(ready.select("node_id", F.col("h2").alias("h")), map_, bias=shift), moved, (map_.size + moved) / 1000)
    # an MLP, then a mean weighted by personalised PageRank
    dense = task.reference(samples, 0, 0)
    removed(ready)
    ranks = B.personalised_pagerank(task.edges, task.test, rounds=2, top=16)
    ranked = written(ranks, "pagerank")
    removed(*getattr(ranks, "_steps", []))
    del ranks
    forgotten()
    spread = lambda: ranked.join(task.infer(dense).select("node_id", "h"), "node_id").groupBy(F.col("seed").alias("node_id")).agg(F.array(*(F.sum(F.col("mass") * F.col("h")[j]) for j in range(task.classes))).alias("h"))
    add("pagerank", dense, spread, 0.0, task.kmacs(dense) + 16 * task.classes / 1000)
    removed(ranked)
    # a student of one layer that learns from the scores of a trained teacher of two
    teacher = task.reference(samples)
    soft = [T.forward(teacher, s.x, T.Mean(len(s.x), s.dst, s.src))[0] for s in samples]
    add("student", task.fit(T.build(task.width, [HIDDEN], task.classes, 0, 1, seed=4), samples, teachers=soft))
    # attention heads whose scores stay as drawn: the products and the classifier are fitted to them
    add("attention", *attention_network(task))
    stats = P.network_grams(teacher, task.inner, task.feats, task.train, task.width, P.full_scheme(0.25, 2), induced=True)
    for eta in (0.25,):
        add(f"self_mean_pruned_{int(1 / eta)}x", task.fit(P.prune_network(teacher, stats, P.full_scheme(eta, 2))[0], samples, ROUNDS // 2))
    task.close()
    return spark.createDataFrame(rows, "model string, micro_f1 double, kmacs double, kmacs_without_preparation double, nodes_per_second double")


def attention_network(task: Task, heads: int = 2, rounds: int = 200):
    """(network, scores, prepared, kMACs): heads drawn at random; the classifier over their
    outputs is fitted on training nodes through a Gram matrix (ridge on one-hot labels)."""
    rng = np.random.default_rng(7)
    draw = lambda a, b: rng.standard_normal((a, b)) * np.sqrt(2.0 / (a + b))
    layer = AttentionLayer([(draw(task.width, HIDDEN), draw(HIDDEN, 1)[:, 0], draw(HIDDEN, 1)[:, 0]) for _ in range(heads)])
    mixed = layer.forward(task.nodes, task.edges, task.feats, task.width)
    hidden = written(mixed, "heads")
    removed(*getattr(mixed, "_steps", []))
    w = layer.f_out
    hot = F.array(*(F.when(F.col("label") == c, 1.0).otherwise(0.0) for c in range(task.classes)))
    both = hidden.join(task.train, "node_id", "left_semi").join(task.labels, "node_id").select("node_id", F.concat("h", F.array(F.lit(1.0)), hot).alias("h"))
    g = P.gram(both, w + 1 + task.classes)
    removed(hidden)
    fitted = np.linalg.solve(g[: w + 1, : w + 1] + 1e-2 * np.trace(g[: w + 1, : w + 1]) / (w + 1) * np.eye(w + 1), g[: w + 1, w + 1 :])
    net = Network([layer], head=fitted[:w], head_bias=fitted[w])
    kmacs = (sum(x.size for x, _, _ in layer.heads) + 2 * heads * task.width + task.n_edges / task.n_nodes * (w + heads) + net.head.size) / 1000
    return net, lambda: infer_full(net, task.nodes, task.edges, task.feats, task.width, persist=True), 0.0, kmacs


def spam_month(spark: SparkSession, folder: str, every: str = "30 minutes", month: int = 10, serve: int = 11, copies: int = 1) -> DataFrame:
    """A month of arriving events, scored in half-hour micro-batches by a model that is
    re-trained monthly: daily accuracy, precision, recall and largest latency (W6, C20).

    An event is spam if the document it names (its id modulo their number) is of low
    quality. The given events span thirty days, so ``month`` is ten of them: the first ten
    train, ``serve`` days after them are served and cross one re-training. A day's arrivals are scored as one micro-batch, their
    features are stored and read by the days after. ``copies`` over-samples the graph."""
    docs = read(spark, folder, "documents").select("doc_id", "text")
    n_docs = docs.count()
    shape = A.shape_features(docs).withColumnRenamed("node_id", "doc")
    labels = read(spark, folder, "labels").filter("quality is not null").select(F.col("doc_id").cast("long").alias("doc"), (F.lit(1) - F.col("quality")).cast("int").alias("label"))
    events = read(spark, folder, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts")).withColumn("doc", F.pmod("event_id", F.lit(n_docs)))
    start = events.agg(F.min("ts")).first()[0]
    events = written(events.filter(F.col("ts") < F.lit(start) + F.expr(f"interval {3 * month} days")), "events")
    feats = written(events.join(shape, "doc").select(F.col("event_id").alias("node_id"), "h"), "event-features")
    links = E.same_user_events(spark, folder)
    if copies > 1:
        more, links = E.replicate(feats, links, copies, 1 << 32)
        feats = written(more, "event-features")
    edges = written(links, "event-edges")
    marks = written(events.join(labels, "doc").select(F.col("event_id").alias("node_id"), "label"), "event-labels")
    width = 8
    feats = written(A.standardize(feats, width)[0], "event-features")
    when = written(events.select(F.col("event_id").alias("node_id"), "ts", F.to_date("ts").alias("day"), F.window("ts", every).start.alias("slot")), "event-times")

    def fit(until):
        past = when.filter(F.col("ts") < F.lit(until)).select("node_id")
        samples = T.sample_subgraphs(past, edges, feats, marks, 2, 700, 2, seed=1)
        return T.train(T.build(width, [HIDDEN, HIDDEN], 2), samples, ROUNDS, decay=1e-3, tol=1e-3)

    # the first month trains
    began = start + datetime.timedelta(days=month)
    net, rows, kept = fit(began), [], None
    days = [r["day"] for r in when.filter(F.col("ts") >= F.lit(began)).select("day").distinct().orderBy("day").limit(serve).collect()]
    service = StreamScorer(net, width, edges, feats, FeatureStore(spark, f"{shared_folder(spark)}/spam-{uuid.uuid4().hex}"), sink=f"{shared_folder(spark)}/spam-scores-{uuid.uuid4().hex}", retrain=lambda _, t: (fit(t), f"at-{t:%Y%m%d}"), every_days=month)
    for number, day in enumerate(days):
        service.on_batch(when.filter(F.col("day") == F.lit(day)).select("node_id", "ts"), number)
    scored = spark.read.parquet(service.sink).withColumn("batch", F.col("stream_batch"))
    pred = predictions(scored).join(marks, "node_id").drop("day").join(when.select("node_id", "day"), "node_id").select("node_id", "pred", "label", F.col("day").alias("served"))
    hit = lambda c: F.sum(c.cast("long"))
    daily = pred.groupBy("served").agg(F.count(F.lit(1)).alias("scored"), F.avg((F.col("pred") == F.col("label")).cast("double")).alias("accuracy"), F.try_divide(hit((F.col("pred") == 1) & (F.col("label") == 1)), hit(F.col("pred") == 1)).alias("precision"), F.try_divide(hit((F.col("pred") == 1) & (F.col("label") == 1)), hit(F.col("label") == 1)).alias("recall"))
    log = service.daily(spark)
    return daily.join(F.broadcast(log.select(F.col("day").alias("served"), "most_ms", "nodes")), "served", "left").withColumnRenamed("served", "day")


def scale_ladder(spark: SparkSession, folder: str, times=(1, 4, 16)) -> DataFrame:
    """Nodes a second, latency and busy share of the slots as the graph is replicated."""
    from prunegraph.plans.headline import WIDTH, base, two_layer

    _, edges, feats = base(spark, folder)
    feats, edges = written(feats, "nodes"), written(edges.select("dst", "src"), "edges")
    rows = []
    for n in times:
        # the copies are made where they are read: no table or file holds them
        more, links = E.replicate(feats, edges, n, 1 << 32)
        with Utilisation(spark) as busy:
            seconds = timed(lambda: infer_full(two_layer(), more.select("node_id"), links, more, WIDTH, persist=True), 1)[0]
        count = more.count()
        rows.append((n, count, count / seconds, 1000 * seconds, busy.share))
    removed(feats, edges)
    return spark.createDataFrame(rows, "copies int, nodes long, nodes_per_second double, latency_ms double, busy_share double")


def memory_limit(spark: SparkSession, folder: str, limit: int = 300_000, sizes=(16, 64, 256)) -> DataFrame:
    """Batches whose raw attributes stay under a byte limit, by batch size."""
    from prunegraph.plans.headline import WIDTH, base, targets_of

    nodes, edges, _ = base(spark, folder)
    edges = written(edges.select("dst", "src"), "edges")
    # batches are cut from one order, so those of the larger sizes are runs of the smallest ones
    least = min(sizes)
    if any(size % least for size in sizes):
        raise ValueError("sizes must be multiples of the least")
    _, _, _, made = expansion(make_batches(targets_of(nodes), least), edges, 2, {2: 32}, lowest=2)
    found = read_counts(written(made[1], "made"), written(neighbour_lists(edges, 32), "lists"), tuple(size // least for size in sizes))
    of = found.withColumn("bytes", F.col("read") * 4 * WIDTH).groupBy((F.col("times") * least).cast("int").alias("size"))
    return of.agg(F.count(F.lit(1)).alias("batches"), F.sum((F.col("bytes") <= limit).cast("long")).alias("fitting"), F.max("bytes").alias("most_bytes"))


def queries() -> dict:
    return {
        "workload_full_inference": lambda s, d: full_inference(s, d, graphs=("purchase",)),
        "workload_copurchase": lambda s, d: full_inference(s, d, (0.25,), graphs=("copurchase",)),
        "workload_batched_inference": batched_inference,
        "workload_batched_copurchase": lambda s, d: batched_inference(s, d, etas=(0.25,), graphs=("copurchase",)),
        "workload_selectors": selector_ablation,
        "workload_batch_sizes": lambda s, d: batch_sizes(s, d, (64, 512, 2048)),
        "workload_store_fractions": store_fractions,
        "workload_architectures": architectures,
        "workload_multilabel": lambda s, d: full_inference(s, d, (0.25,), multilabel=True, graphs=("purchase",)),
        "workload_high_test_share": lambda s, d: full_inference(s, d, (0.25,), train=8, val=12, graphs=("copurchase",)),
        "workload_chain": lambda s, d: full_inference(s, d, (0.25,), graphs=("chain", "doc")),
        "workload_spam_month": spam_month,
        "workload_scale_ladder": scale_ladder,
        "workload_memory_limit": memory_limit,
    }


def oracle_sql() -> dict[str, str]:
    return {}
