"""Reading and writing the engine's tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

NODE_KINDS = {"customer": 0, "part": 1, "order": 2, "supplier": 3}


def read(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """One of the given tables; columns are pruned by whoever uses it."""
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_as(spark: SparkSession, path: str, kind: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV, JSON or text; CSV and JSON need a schema (no inference)."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} is read with an explicit schema")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", mode: str = "error", partition_by: list[str] | None = None) -> None:
    writer = df.write.format(kind).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int, path: str | None = None, mode: str = "error") -> None:
    """A catalog table bucketed and sorted by ``keys``: joins and aggregations on them need no shuffle."""
    writer = df.write.mode(mode).bucketBy(buckets, *keys).sortBy(*keys)
    (writer.option("path", path) if path else writer).saveAsTable(name)


def node_ids(spark: SparkSession, folder: str, kinds: tuple[str, ...] = ("customer", "part")) -> DataFrame:
    """node_id of every row of the node tables; kinds share one id space."""
    keys = {"customer": "c_custkey", "part": "p_partkey", "order": "o_orderkey", "supplier": "s_suppkey"}
    names = {"order": "orders"}
    found = None
    for kind in kinds:
        ids = read(spark, folder, names.get(kind, kind)).select((F.col(keys[kind]) * 4 + NODE_KINDS[kind]).cast("long").alias("node_id"))
        found = ids if found is None else found.unionByName(ids)
    return found


def validate_edges(edges: DataFrame) -> DataFrame:
    """A report row: duplicate pairs, self edges, null ends."""
    return edges.groupBy("dst", "src").agg(F.count(F.lit(1)).alias("n")).agg(
        F.coalesce(F.sum((F.col("n") > 1).cast("long")), F.lit(0)).alias("duplicate_pairs"),
        F.coalesce(F.sum((F.col("dst") == F.col("src")).cast("long")), F.lit(0)).alias("self_edges"),
        F.coalesce(F.sum((F.col("dst").isNull() | F.col("src").isNull()).cast("long")), F.lit(0)).alias("null_ends"),
    )


def validate_features(feats: DataFrame, width: int) -> DataFrame:
    """A report row: ragged, null and non-finite vectors."""
    bad = F.exists("h", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return feats.agg(
        F.coalesce(F.sum((F.size("h") != width).cast("long")), F.lit(0)).alias("ragged"),
        F.coalesce(F.sum(F.col("h").isNull().cast("long")), F.lit(0)).alias("missing"),
        F.coalesce(F.sum(F.coalesce(bad, F.lit(False)).cast("long")), F.lit(0)).alias("not_finite"),
    )
