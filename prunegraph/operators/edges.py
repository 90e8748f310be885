"""Graphs from ordinary tables: (dst, src), dst gathers from src, pairs are distinct."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.sources.tables import read


def both_ways(pairs: DataFrame) -> DataFrame:
    """Pairs (a, b) as edges in both directions."""
    return pairs.select(F.col("a").alias("dst"), F.col("b").alias("src")).unionByName(pairs.select(F.col("b").alias("dst"), F.col("a").alias("src")))


def _lines(spark, folder):
    return read(spark, folder, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")


def purchase(spark: SparkSession, folder: str) -> DataFrame:
    """Customers and the parts they ordered."""
    orders = read(spark, folder, "orders").select("o_orderkey", "o_custkey")
    pairs = _lines(spark, folder).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select((F.col("o_custkey") * 4).alias("a"), (F.col("l_partkey") * 4 + 1).alias("b")).distinct()
    return both_ways(pairs)


def copurchase(spark: SparkSession, folder: str) -> DataFrame:
    """Parts in one order."""
    once = _lines(spark, folder).select("l_orderkey", "l_partkey").distinct()
    other = once.select("l_orderkey", F.col("l_partkey").alias("q"))
    return once.join(other, "l_orderkey").filter("l_partkey <> q").select((F.col("l_partkey") * 4 + 1).alias("dst"), (F.col("q") * 4 + 1).alias("src")).distinct()


def chain(spark: SparkSession, folder: str) -> DataFrame:
    """Customers, their orders, the parts of those."""
    first = read(spark, folder, "orders").select((F.col("o_custkey") * 4).alias("a"), (F.col("o_orderkey") * 4 + 2).alias("b"))
    second = _lines(spark, folder).select((F.col("l_orderkey") * 4 + 2).alias("a"), (F.col("l_partkey") * 4 + 1).alias("b"))
    return both_ways(first.unionByName(second).distinct())


def supply(spark: SparkSession, folder: str) -> DataFrame:
    """Suppliers and the parts they delivered."""
    return both_ways(_lines(spark, folder).select((F.col("l_suppkey") * 4 + 3).alias("a"), (F.col("l_partkey") * 4 + 1).alias("b")).distinct())


def same_user_events(spark: SparkSession, folder: str) -> DataFrame:
    """An event gathers from the same user's events of the day before it.

    The range join runs on (user, day) and its neighbour day, so only two days meet."""
    events = read(spark, folder, "events").select("event_id", "user_id", "ts").withColumn("day", F.to_date("ts"))
    old = events.select("user_id", F.col("event_id").alias("src"), F.col("ts").alias("old_ts"), F.explode(F.array(F.col("day"), F.date_add("day", 1))).alias("day"))
    near = events.join(old, ["user_id", "day"])
    return near.filter("old_ts < ts and old_ts >= ts - interval 1 day").select(F.col("event_id").alias("dst"), "src")


def replies(spark: SparkSession, folder: str) -> DataFrame:
    """Neighbouring turns of a conversation."""
    turns = read(spark, folder, "conversations").select("conv_id", "turn")
    step = turns.select("conv_id", F.col("turn").alias("turn"), F.explode(F.array(F.col("turn") - 1, F.col("turn") + 1)).alias("other"))
    there = turns.select("conv_id", F.col("turn").alias("other"))
    return step.join(there, ["conv_id", "other"], "left_semi").select((F.col("conv_id") * 64 + F.col("turn")).alias("dst"), (F.col("conv_id") * 64 + F.col("other")).alias("src"))


def rare_tokens(spark: SparkSession, folder: str, most: int = 12, least_shared: int = 2) -> DataFrame:
    """Documents that share at least ``least_shared`` tokens held by 2 to ``most`` documents."""
    words = F.array_distinct(F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: F.length(w) > 2))
    held = read(spark, folder, "documents").select("doc_id", F.explode(words).alias("token"))
    few = held.groupBy("token").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n").between(2, most)).select("token")
    kept = held.join(few, "token")
    other = kept.select("token", F.col("doc_id").alias("src"))
    return kept.join(other, "token").filter("doc_id <> src").groupBy(F.col("doc_id").alias("dst"), "src").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= least_shared).select("dst", "src")


def nearest_vectors(spark: SparkSession, folder: str, k: int = 8, block: int = 512) -> DataFrame:
    """Each vector gathers from its ``k`` largest dot products (exact, in blocks of queries)."""
    import numpy as np
    import pyarrow as pa

    vectors = read(spark, folder, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    # every query against blocks of vectors: the best k of each block, then of all
    blocks = max(1, -(-vectors.count() // block))
    left = vectors.withColumn("lb", F.pmod("vec_id", F.lit(blocks)).cast("int"))
    # a query block and a vector block meet in one task
    left = left.withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    asks = vectors.select("vec_id", "v", F.pmod("vec_id", F.lit(blocks)).cast("int").alias("qb"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("lb"))

    def rank(key, x, q):
        empty = pa.table([pa.array([], pa.int64()), pa.array([], pa.int64()), pa.array([], pa.int64())], ["dst", "src", "dot"])
        if not x.num_rows or not q.num_rows:
            return empty
        a, b = (np.array(t.column("v").to_pylist()) for t in (x, q))
        dot = np.floor((b @ a.T) * 1e6 + 0.4999).astype(np.int64)
        ids, asked = x.column("vec_id").to_numpy(), q.column("vec_id").to_numpy()
        dot[asked[:, None] == ids[None, :]] = -(1 << 40)
        order = np.lexsort((np.broadcast_to(ids, dot.shape), -dot), axis=1)[:, : k + 1]
        s = np.take_along_axis(dot, order, 1)
        keep = s > -(1 << 40)
        return pa.table([pa.array(np.broadcast_to(asked[:, None], order.shape)[keep]), pa.array(ids[order][keep]), pa.array(s[keep])], ["dst", "src", "dot"])

    found = left.groupBy("lb", "qb").cogroup(asks.groupBy("lb", "qb")).applyInArrow(rank, "dst long, src long, dot long")
    w = Window.partitionBy("dst").orderBy(F.desc("dot"), "src")
    return found.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= k).select("dst", "src")


def hyperlinks(spark: SparkSession, folder: str) -> DataFrame:
    """page_id and the targets of its links, distinct."""
    found = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)
    return read(spark, folder, "pages").select("page_id", F.explode(F.array_distinct(found)).alias("target"))


def replicate(nodes: DataFrame, edges: DataFrame, times: int, stride: int) -> tuple[DataFrame, DataFrame]:
    """``times`` disjoint copies; copy r has ids + r * stride."""
    copies = nodes.sparkSession.range(times).select((F.col("id") * stride).alias("shift"))
    more = nodes.crossJoin(F.broadcast(copies)).withColumn("node_id", F.col("node_id") + F.col("shift")).drop("shift")
    links = edges.crossJoin(F.broadcast(copies)).select((F.col("dst") + F.col("shift")).alias("dst"), (F.col("src") + F.col("shift")).alias("src"))
    return more, links


def split_of(node: str = "node_id", train: int = 60, val: int = 75):
    """train, val or test by an arithmetic hash both engines share."""
    h = F.pmod(F.pmod(F.pmod(F.col(node), F.lit(65536)) * 40503, F.lit(65536)), F.lit(100))
    return F.when(h < train, "train").when(h < val, "val").otherwise("test")


def inside(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges with both ends in ``nodes``: the inductive training graph."""
    ids = nodes.select("node_id")
    return edges.join(ids.withColumnRenamed("node_id", "dst"), "dst", "left_semi").join(ids.withColumnRenamed("node_id", "src"), "src", "left_semi").select("dst", "src")
