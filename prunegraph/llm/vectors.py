"""Cleaning and collapsing of vector tables, shared by search and deduplication."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def matrix(column: pa.Array | pa.ChunkedArray, kind=np.float64) -> np.ndarray:
    """Equally long lists as a matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).astype(kind).reshape(n, -1) if n else np.zeros((0, 0), kind)


def lists(x: np.ndarray, kind=pa.float64()) -> pa.Array:
    n, d = x.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * d), pa.array(np.ascontiguousarray(x).ravel(), kind))


def clean(df: DataFrame, vector: str = "embedding") -> DataFrame:
    """vec_id, vector (double), other columns; only usable vectors.

    Null and empty vectors, zero vectors and those with null or non-finite components
    are left out."""
    v = F.col(vector).cast("array<double>")
    norm = F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x)
    return df.withColumn("vector", v).filter("vec_id is not null").filter(F.size("vector") > 0).filter(
        norm.isNotNull() & ~F.isnan(norm) & (norm > 0) & (norm < float("inf"))
    )


def collapse(vectors: DataFrame, by: list[str], ids: int) -> DataFrame:
    """Equal vectors (and ``by``) as one row: their least different ids and their number of rows.

    Rows of one vector are joined per task before they are shuffled, so a vector that a
    third of the table repeats reaches its group as a row per task."""

    def run(batches):
        for batch in batches:
            names = batch.schema.names
            groups: dict = {}
            vec, vid = batch.column(names.index("vector")), batch.column(names.index("vec_id")).to_pylist()
            extra = list(zip(*(batch.column(names.index(b)).to_pylist() for b in by))) if by else [()] * batch.num_rows
            flat, at = vec.flatten().to_numpy(zero_copy_only=False), vec.offsets.to_numpy()
            flat = flat + 0.0  # -0.0 and 0.0 are one value
            for i in range(batch.num_rows):
                data = flat[at[i] - at[0] : at[i + 1] - at[0]].tobytes()
                groups.setdefault((extra[i], data), []).append(vid[i])
            rows = [(hashlib.blake2b(data, digest_size=16).digest(), np.frombuffer(data).tolist(), sorted(set(v))[:ids], len(v), *e) for (e, data), v in groups.items()]
            c = list(zip(*rows))
            if c:
                kinds = [pa.binary(), pa.list_(pa.float64()), pa.list_(pa.int64()), pa.int64()]
                yield pa.RecordBatch.from_arrays([*(pa.array(x, k) for x, k in zip(c, kinds)), *(pa.array(x, batch.schema.field(b).type) for x, b in zip(c[4:], by))], ["print", "vector", "ids", "n", *by])

    types = dict(vectors.dtypes)
    schema = "print binary, vector array<double>, ids array<long>, n long" + "".join(f", {b} {types[b]}" for b in by)
    once = vectors.select("vec_id", "vector", *by).withColumn("vec_id", F.col("vec_id").cast("long")).mapInArrow(run, schema)
    return once.groupBy("print", *by).agg(F.first("vector").alias("vector"), F.slice(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))), 1, ids).alias("ids"), F.sum("n").alias("n")).withColumn("rep", F.col("ids")[0])
