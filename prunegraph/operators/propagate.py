"""Neighbour aggregation as a join and a partial aggregate (M1-M3, M5).

Feature frames are (node_id, h array<double>), optionally with group columns such as
batch_id. Edges carry an optional weight ``w``; without one, a node takes the plain
mean over its neighbours. Three layouts give the same result: "array" sums vectors
with the JVM's summarizer, "wide" has a column per channel inside generated code, "long"
has a row per channel and is the readable reference.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WIDE_CHANNELS = 64


def normalize(edges: DataFrame, how: str = "row_mean") -> DataFrame:
    """Edges with weights ``w``: row_mean, sym, self_loop_mean, sum or weighted."""
    if how == "self_loop_mean":
        loops = edges.select("dst").unionByName(edges.select(F.col("src").alias("dst"))).distinct().select("dst", F.col("dst").alias("src"))
        edges = edges.select("dst", "src").unionByName(loops).distinct()
        how = "row_mean"
    if how == "sum":
        return edges.select("dst", "src", F.lit(1.0).alias("w"))
    if how == "weighted":
        total = edges.groupBy("dst").agg(F.sum("w").alias("t"))
        return edges.join(total, "dst").select("dst", "src", F.try_divide("w", "t").alias("w"))
    degree = edges.groupBy("dst").agg(F.count(F.lit(1)).alias("n"))
    own = edges.join(degree, "dst")
    if how == "row_mean":
        return own.select("dst", "src", (F.lit(1.0) / F.col("n")).alias("w"))
    if how == "sym":
        there = degree.select(F.col("dst").alias("src"), F.col("n").alias("m"))
        return own.join(there, "src", "left").select("dst", "src", (1.0 / F.sqrt(F.col("n") * F.coalesce("m", F.lit(1)))).alias("w"))
    raise ValueError(how)


def select_channels(feats: DataFrame, kept: list[int], column: str = "h") -> DataFrame:
    """Keep the listed channels, in that order."""
    picked = F.transform(F.array(*(F.lit(int(j)) for j in kept)), lambda j: F.element_at(column, j + 1)) if kept else F.array().cast("array<double>")
    return feats.withColumn(column, picked)


def to_long(feats: DataFrame) -> DataFrame:
    keep = [c for c in feats.columns if c != "h"]
    return feats.select(*keep, F.posexplode("h").alias("ch", "x"))


def to_wide(feats: DataFrame, width: int) -> DataFrame:
    keep = [c for c in feats.columns if c != "h"]
    return feats.select(*keep, *(F.col("h")[j].alias(f"c{j:04d}") for j in range(width)))


def from_wide(wide: DataFrame, width: int) -> DataFrame:
    names = [f"c{j:04d}" for j in range(width)]
    return wide.select(*(c for c in wide.columns if c not in names), F.array(*names).alias("h"))


def zeros(width: int) -> Column:
    return F.array_repeat(F.lit(0.0), width)


def propagate(edges: DataFrame, feats: DataFrame, width: int, nodes: DataFrame | None = None, layout: str = "auto", group: str | None = None) -> DataFrame:
    """One step: (node_id, h) for every dst; with ``nodes``, zero for those without neighbours.

    ``group`` names a column that edges and features share (batches in one job)."""
    weighted = "w" in edges.columns
    keys = [group] if group else []
    if layout == "auto":
        layout = "wide" if width <= WIDE_CHANNELS else "array"
        # edges of ``blocked``, which many propagations share
        if width > 0 and not keys and not weighted and hasattr(edges, "_blocks"):
            layout = "blocks"
    side = feats.withColumnRenamed("node_id", "src").select(*keys, "src", "h")
    joined = edges.join(side, [*keys, "src"])
    by = [*keys, F.col("dst").alias("node_id")]
    if layout == "blocks":
        out = edges._blocks.mean(feats, width)
    elif width == 0:
        out = joined.select(*by).distinct().withColumn("h", zeros(0))
    elif layout == "wide":
        one = lambda j: F.sum(F.col("w") * F.col("h")[j]) if weighted else F.avg(F.col("h")[j])
        out = joined.groupBy(*by).agg(*(one(j).alias(f"c{j:04d}") for j in range(width)))
        out = from_wide(out, width)
    elif layout == "array":
        from pyspark.ml.functions import array_to_vector, vector_to_array
        from pyspark.ml.stat import Summarizer

        v = array_to_vector("h")
        if weighted:
            # sum of w * h = weighted mean times sum of w; zero weights are left out of both
            pos = joined.filter("w <> 0").withColumn("v", array_to_vector(F.transform("h", lambda x: x * F.col("w"))))
            out = pos.groupBy(*by).agg(vector_to_array(Summarizer.sum(F.col("v"))).alias("h"))
        else:
            out = joined.withColumn("v", v).groupBy(*by).agg(vector_to_array(Summarizer.mean(F.col("v"))).alias("h"))
    elif layout == "long":
        rows = to_long(joined)
        value = F.sum(F.col("w") * F.col("x")) if weighted else F.avg("x")
        cells = rows.groupBy(*by, "ch").agg(value.alias("x"))
        out = cells.groupBy(*keys, "node_id").agg(F.sort_array(F.collect_list(F.struct("ch", "x"))).alias("cells")).select(*keys, "node_id", F.col("cells.x").alias("h"))
    else:
        raise ValueError(layout)
    if nodes is None:
        return out
    return nodes.select(*keys, "node_id").join(out, [*keys, "node_id"], "left").withColumn("h", F.coalesce("h", zeros(width)))


def propagate_k(edges: DataFrame, feats: DataFrame, k: int, width: int, nodes: DataFrame | None = None, **how) -> list[DataFrame]:
    """[h, Ah, ..., A^k h]; a power of A is never formed."""
    out = [feats]
    for _ in range(k):
        out.append(propagate(edges, out[-1], width, nodes, **how))
    return out
