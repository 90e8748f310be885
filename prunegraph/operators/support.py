"""Batched inference: batches, support sets, caps and stored features."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.operators.layers import Network, dense_product
from prunegraph.operators.propagate import select_channels
from prunegraph.sources.shared import removed, written

#: Produced nodes whose neighbours one task of ``read_counts`` counts.
COUNTED_AT_ONCE = 50_000


def hash_of(node: str = "node_id"):
    return F.pmod(F.pmod(F.col(node), F.lit(65536)) * 40503, F.lit(65536))


def make_batches(targets: DataFrame, size: int, spread: int = 1 << 22) -> DataFrame:
    """batch_id, node_id: random batches that cover the targets, each of ``size`` but the last.

    The order is an arithmetic hash, then the id. Ranks come from counts per bucket and a
    window inside each bucket, so no sort over all targets is needed: a bucket is a hash
    value and a range of ``spread`` ids, so it holds ``spread`` / 65536 targets at most."""
    rows = targets.select("node_id").withColumn("h", hash_of()).withColumn("b", F.floor(F.col("node_id") / spread))
    counts = rows.groupBy("h", "b").agg(F.count(F.lit(1)).alias("n"))
    # sums over hash values (65,536 at most), then over the buckets of one
    ahead = Window.partitionBy(F.lit(0)).orderBy("h").rowsBetween(Window.unboundedPreceding, -1)
    values = counts.groupBy("h").agg(F.sum("n").alias("n")).withColumn("ahead", F.coalesce(F.sum("n").over(ahead), F.lit(0))).select("h", "ahead")
    inside = Window.partitionBy("h").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    start = counts.join(values, "h").select("h", "b", (F.col("ahead") + F.coalesce(F.sum("n").over(inside), F.lit(0))).alias("first"))
    rank = F.row_number().over(Window.partitionBy("h", "b").orderBy("node_id")) - 1
    return rows.withColumn("r", rank).join(start, ["h", "b"]).select(F.floor((F.col("first") + F.col("r")) / size).cast("int").alias("batch_id"), "node_id")


def capped(edges: DataFrame, keys: list[str], most: int) -> DataFrame:
    """At most ``most`` neighbours a node: least hash of the pair, then least id."""
    h = F.pmod(F.pmod(F.col("src"), F.lit(65536)) * 40503 + F.col("dst"), F.lit(65536))
    w = Window.partitionBy(*keys).orderBy(h, "src")
    return edges.withColumn("_r", F.row_number().over(w)).filter(F.col("_r") <= most).drop("_r")


def expand(produced: DataFrame, edges: DataFrame, cap: int | None) -> DataFrame:
    """(batch_id, dst, src) of the produced nodes.

    Which neighbours a cap keeps does not depend on the batch, so a node's edges are
    capped once, before they are copied to the batches that need them."""
    if cap:
        wanted = produced.select(F.col("node_id").alias("dst")).distinct()
        edges = capped(edges.join(wanted, "dst", "left_semi"), ["dst"], cap)
    return edges.join(produced.select("batch_id", F.col("node_id").alias("dst")), "dst").select("batch_id", "dst", "src")


def support_sets(batches: DataFrame, edges: DataFrame, layers: int, caps: dict[int, int] | None = None, store: DataFrame | None = None) -> tuple[DataFrame, dict[int, DataFrame], dict[int, DataFrame]]:
    """Rows (batch_id, layer, node_id, role), the edges used per layer and what the store gives."""
    return expansion(batches, edges, layers, caps, store)[:3]


def expansion(batches: DataFrame, edges: DataFrame, layers: int, caps: dict[int, int] | None = None, store: DataFrame | None = None, lowest: int = 1):
    """As ``support_sets``, and the nodes each layer produces (0: whose attributes are read).

    ``layer`` is the output that is needed: targets at the top, then their own lower
    output ("self") and that of neighbours without a stored feature ("unvisited").
    "visited" neighbours are read from the store and not expanded. The hop of layer i is
    ``layers`` - i + 1; ``caps`` is by hop. The store never holds raw attributes. Edges and
    the ids of every layer are written once, so each step's plan starts at small tables.
    Layers below ``lowest`` are left to the caller."""
    edges = edges if hasattr(edges, "_written_path") else written(edges.select("dst", "src"), "edges")
    produced = written(batches.select("batch_id", "node_id").distinct(), "targets")
    rows = produced.select("batch_id", F.lit(layers).alias("layer"), "node_id", F.lit("target").alias("role"))
    used, given, made = {}, {}, {layers: produced}
    for layer in range(layers, lowest - 1, -1):
        links = written(expand(produced, edges, (caps or {}).get(layers - layer + 1)), "links")
        used[layer] = links
        near = links.select("batch_id", F.col("src").alias("node_id")).distinct()
        others = near.join(produced, ["batch_id", "node_id"], "left_anti")
        if store is not None and layer > 1:
            stored = store.filter(F.col("layer") == layer - 1).select("node_id").distinct().withColumn("stored", F.lit(True))
            others = written(others.join(stored, "node_id", "left").select("batch_id", "node_id", F.coalesce("stored", F.lit(False)).alias("stored")), "others")
            visited, unvisited = others.filter("stored").drop("stored"), others.filter("not stored").drop("stored")
            rows = rows.unionByName(visited.select("batch_id", F.lit(layer - 1).alias("layer"), "node_id", F.lit("visited").alias("role")))
            given[layer - 1] = visited
        else:
            unvisited = written(others, "others")
        rows = rows.unionByName(produced.select("batch_id", F.lit(layer - 1).alias("layer"), "node_id", F.lit("self").alias("role")))
        rows = rows.unionByName(unvisited.select("batch_id", F.lit(layer - 1).alias("layer"), "node_id", F.lit("unvisited").alias("role")))
        produced = produced.unionByName(unvisited.select("batch_id", "node_id"))
        made[layer - 1] = produced
    return rows, used, given, made


def neighbour_lists(edges: DataFrame, cap: int | None = None) -> DataFrame:
    """(node_id, least, near, far): every node's neighbours, capped once for whatever batches need it.

    ``near`` holds them as 32-bit distances from ``least``; where one does not fit, ``far``
    holds the ids themselves instead."""
    rows = capped(edges.select("dst", "src"), ["dst"], cap) if cap else edges
    lists = rows.groupBy(F.col("dst").alias("node_id")).agg(F.min("src").alias("least"), F.max("src").alias("most"), F.collect_list("src").alias("ids"))
    fits = F.coalesce(F.try_subtract("most", "least") < F.lit(1 << 31), F.lit(False))
    return lists.select("node_id", "least", F.when(fits, F.transform("ids", lambda x: (x - F.col("least")).cast("int"))).alias("near"), F.when(~fits, F.col("ids")).alias("far"))


def read_counts(made: DataFrame, lists: DataFrame, sizes: tuple[int, ...] = (1,), rows: int | None = None) -> DataFrame:
    """(times, batch_id, made, links, read): per batch, the rows of ``made``, the edges into
    them and the distinct nodes these and their neighbours are.

    ``times`` joins that many batches in a row into one (1: as they are), so batches of several
    sizes over the same targets are counted in one pass. Nodes meet their lists once; a
    task holds the distinct nodes of its batches, so nothing is written a (batch, node)."""
    most = max(sizes)
    rows = made.count() if rows is None else rows
    joined = made.select("batch_id", "node_id").join(lists.hint("merge"), "node_id", "left")
    parts = max(int(made.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-rows // COUNTED_AT_ONCE))
    dealt = joined.select(F.col("batch_id").cast("long"), "node_id", "least", "near", "far", F.floor(F.col("batch_id") / most).alias("g")).repartition(parts, "g")

    def distinct(batch, node):
        order = np.lexsort((node, batch))
        batch, node = batch[order], node[order]
        first = np.ones(len(batch), bool)
        first[1:] = (batch[1:] != batch[:-1]) | (node[1:] != node[:-1])
        return batch[first], node[first]

    def count(blocks):
        held, waiting, n, made_, links = (np.zeros(0, np.int64), np.zeros(0, np.int64)), [], 0, {}, {}
        for block in blocks:
            batch, node = block.column(0).to_numpy(), block.column(1).to_numpy()
            least = block.column(2).fill_null(0).to_numpy(zero_copy_only=False)
            near, far = (block.column(i).value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64) for i in (3, 4))
            length = near + far
            for b, m, e in zip(*(x.tolist() for x in _sums(batch, length))):
                made_[b], links[b] = made_.get(b, 0) + m, links.get(b, 0) + e
            flat, ids = (block.column(i).flatten().to_numpy(zero_copy_only=False).astype(np.int64) for i in (3, 4))
            waiting += [(batch, node), (np.repeat(batch, near), flat + np.repeat(least, near)), (np.repeat(batch, far), ids)]
            n += len(batch) + int(length.sum())
            if n > 2_000_000:
                held, waiting, n = distinct(*(np.concatenate(x) for x in zip(held, *waiting))), [], 0
        batch, node = distinct(*(np.concatenate(x) for x in zip(held, *waiting)))
        for times in sizes:
            b, _ = distinct(batch // times, node) if times > 1 else (batch, node)
            found, read = np.unique(b, return_counts=True)
            of = {int(x): [0, 0] for x in found}
            for x in made_:
                of[x // times][0] += made_[x]
                of[x // times][1] += links[x]
            columns = [np.full(len(found), times), found, np.array([of[int(x)][0] for x in found], np.int64), np.array([of[int(x)][1] for x in found], np.int64), read]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["times", "batch_id", "made", "links", "read"])

    return dealt.drop("g").mapInArrow(count, "times long, batch_id long, made long, links long, read long")


def _sums(batch: np.ndarray, length: np.ndarray):
    """Batches of a block, their rows and their edges."""
    found, at, rows = np.unique(batch, return_inverse=True, return_counts=True)
    return found, rows, np.bincount(at, length, len(found)).astype(np.int64)


def shared_support(layers: int, asked: DataFrame, edges: DataFrame, caps: dict[int, int] | None = None, depth: int | None = None) -> tuple[dict[int, DataFrame], dict[int, DataFrame]]:
    """By layer, the nodes ``infer_shared`` makes for the ``asked`` ones and the edges it uses.

    They depend on no weights, so networks that differ in these only can share them.
    Joins with node lists are by sorting, as the lists are as long as the graph may be."""
    depth = layers if depth is None else depth
    caps = caps or {}
    made, used = {layers: written(asked.select("node_id").distinct(), "asked")}, {}
    for i in range(layers, 0, -1):
        links = edges.join(made[i].select(F.col("node_id").alias("dst")).hint("merge"), "dst", "left_semi").select("dst", "src")
        cap = caps.get(depth - i + 1)
        # a cut is worked out once; all edges are read where they are
        used[i] = written(capped(links, ["dst"], cap), "links") if cap else links
        if i > 1:
            made[i - 1] = written(made[i].unionByName(used[i].select(F.col("src").alias("node_id"))).distinct(), "asked")
    return made, used


def infer_shared(layers: list, asked: DataFrame, edges: DataFrame, feats: DataFrame, width: int, caps: dict[int, int] | None = None, depth: int | None = None, support=None) -> DataFrame:
    """(node_id, h) of the ``asked`` nodes after ``layers``, the lowest of ``depth``: each node once a layer.

    Nothing here depends on a batch: caps do not, and attributes are never stored. ``support``
    is the ``shared_support`` where the caller has it, and keeps it."""
    made, used = support or shared_support(len(layers), asked, edges, caps, depth)
    h, w, before = feats.select("node_id", "h"), width, None
    for i, layer in enumerate(layers, start=1):
        h = written(layer.forward(made[i].hint("merge"), used[i], h.hint("merge"), w).select("node_id", "h"), "features")
        w = layer.f_out
        removed(*([before] if before is not None else []), *((made[i], used[i]) if support is None else ()))
        before = h
    return h


def infer_batched(net: Network, batches: DataFrame, edges: DataFrame, feats: DataFrame, width: int, caps: dict[int, int] | None = None, store: DataFrame | None = None, grown=None, support=None) -> DataFrame:
    """(batch_id, node_id, h) of the targets; all batches in one job a layer.

    ``feats`` is (node_id, h); ``store`` is (layer, node_id, h) of middle outputs. A layer's
    outputs that are the same in every batch are made once and shared: all layers without
    a store, the first with one (above it, a batch's own nodes are computed and
    not read from the store, so outputs differ between batches). ``grown`` is the ``expansion``
    down to layer 2 where the caller has it, ``support`` the ``shared_support`` below that."""
    depth = len(net.layers)
    shared = depth if store is None else min(1, depth)
    edges = edges if hasattr(edges, "_written_path") else written(edges.select("dst", "src"), "edges")
    if shared == depth:
        used, given, made = {}, {}, {depth: written(batches.select("batch_id", "node_id").distinct(), "targets")}
    else:
        _, used, given, made = grown or expansion(batches, edges, depth, caps, store, lowest=shared + 1)
    h, w, before = infer_shared(net.layers[:shared], made[shared], edges, feats, width, caps, depth, support), width, None
    h = made[shared].join(h.hint("merge"), "node_id")
    for i in range(shared, depth + 1):
        if i > shared:
            h = written(h.select("batch_id", "node_id", "h"), "features")
            removed(*([before] if before is not None else []))
            before = h
            h = net.layers[i - 1].forward(made[i], used[i], h, w, group="batch_id")
        w = net.layers[i - 1].f_out if i else w
        if i in given:
            kept = store.filter(F.col("layer") == i).select("node_id", "h")
            h = h.select("batch_id", "node_id", "h").unionByName(given[i].join(kept, "node_id").select("batch_id", "node_id", "h"))
    if net.head is not None:
        if net.head_kept is not None:
            h = select_channels(h, net.head_kept)
        h = dense_product(h, net.head, bias=net.head_bias)
    return h


def infer(net: Network, nodes: DataFrame, targets: DataFrame, edges: DataFrame, feats: DataFrame, width: int, dims: list[tuple[int, dict[int, int]]], degree: float, regime: str = "auto", size: int = 512) -> DataFrame:
    """Full or batched, by the smaller estimated cost over all targets."""
    from prunegraph.functions.cost import batched_macs, full_macs
    from prunegraph.operators.layers import infer_full

    if regime == "auto":
        full = nodes.count() * full_macs(dims, degree)
        regime = "full" if full <= targets.count() * batched_macs(dims, degree) else "batched"
    if regime == "full":
        return infer_full(net, nodes, edges, feats, width).join(targets.select("node_id"), "node_id", "left_semi")
    return infer_batched(net, make_batches(targets, size), edges, feats, width).drop("batch_id")
