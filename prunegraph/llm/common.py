"""Shared parts: shared-folder tables, Arrow text buffers, hashing, components."""

from __future__ import annotations

import ctypes
import os
import uuid
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

LOCAL_DEFAULT = "/tmp/checkpoints/prunegraph"
CHUNK_BYTES = 2 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share; a local one only where none is configured (tests)."""
    return spark.conf.get("spark.checkpoint.dir", None) or os.environ.get("SPARK_CHECKPOINT_DIR") or LOCAL_DEFAULT


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write to the shared folder as Parquet and read that back.

    What is lost with an executor is read again from the shared folder."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back._prunegraph_path = path
    return back


def discard(*frames: DataFrame) -> None:
    """Remove tables written by ``materialize`` that no later plan reads."""
    for df in frames:
        path = getattr(df, "_prunegraph_path", None)
        if path:
            jvm = df.sparkSession.sparkContext._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


def free_name(df: DataFrame, name: str) -> str:
    """``name``, or a longer one where ``df`` has such a column (in any letter case)."""
    taken = {c.lower() for c in df.columns}
    while name in taken:
        name += "_"
    return name


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def width(spark: SparkSession) -> int:
    """Shuffle partitions of the session: the number of salts a hot key is split into."""
    return max(16, int(spark.conf.get("spark.sql.shuffle.partitions")))


def salt(*cols: Column, n: int) -> Column:
    return F.pmod(F.xxhash64(*cols, F.lit(77)), F.lit(n)).cast("int")


def with_copy(rows: DataFrame, keys: list[str]) -> DataFrame:
    """``rows`` with "copy": 0 where ``keys`` are unique, else a number of the row.

    ``rows`` must be a written table, so that the numbers hold. Copies of one row can
    then be spread, however many there are."""
    again = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("copies")).filter("copies > 1")
    if again.isEmpty():
        return rows.withColumn("copy", F.lit(0).cast("long"))
    numbered = rows.withColumn("copy", F.monotonically_increasing_id() + 1)
    side = again.select(*(F.col(k).alias(f"again_{k}") for k in keys))
    same = [numbered[k].eqNullSafe(side[f"again_{k}"]) for k in keys]
    marked = numbered.join(side.withColumn("again", F.lit(True)), same, "left")
    return marked.withColumn("copy", F.when(F.col("again"), F.col("copy")).otherwise(0)).select(*rows.columns, "copy")


# ---------------------------------------------------------------- workers' memory

_clear: list[Callable[[], None]] = []


def cleared_after_task(clear: Callable[[], None]) -> Callable[[], None]:
    """Register what empties a cache that a module keeps between the batches of a task."""
    _clear.append(clear)
    return clear


def give_back() -> None:
    """Return what the allocators of this worker hold for later; a worker outlives its tasks."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim is not None:
        trim(0)


def tidied(batches):
    """``batches``; after the last one the worker gives back the memory it keeps for a next task."""
    try:
        yield from batches
    finally:
        for clear in _clear:
            clear()
        give_back()


def tidy(kernel):
    """``kernel`` for ``mapInArrow``, ``tidied``."""
    return lambda batches: tidied(kernel(batches))


# ---------------------------------------------------------------- Arrow text


def utf8(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and int64 offsets (one more than rows) of a string column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return utf8_of(pc.fill_null(column, "").cast(pa.large_string()))


def utf8_of(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """As ``utf8``, for strings or bytes without nulls."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.type not in (pa.large_string(), pa.large_binary()):
        column = column.cast(pa.large_string() if pa.types.is_string(column.type) else pa.large_binary())
    n = len(column)
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1]
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None and at[-1] > at[0] else np.zeros(0, np.uint8)
    return raw, at - at[0]


def slices(offsets: np.ndarray, most: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``most`` bytes; a longer text is a range of its own."""
    row, n = 0, len(offsets) - 1
    while row < n:
        end = int(np.searchsorted(offsets, offsets[row] + most, "right")) - 1
        end = min(max(end, row + 1), n)
        yield row, end
        row = end


def mix(x: np.ndarray) -> np.ndarray:
    """64-bit finaliser (fixed values of the public splitmix64 generator)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def long_view(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def crc32(column: Column) -> Column:
    """Unsigned CRC-32 of the UTF-8 bytes; null counts as empty."""
    return F.crc32(F.coalesce(column, F.lit("")).cast("binary"))


def crc32_bytes(data: bytes) -> int:
    return zlib.crc32(data)


# ---------------------------------------------------------------- components

#: Links a task holds before it passes on their stars.
MOST_LINKS = 1 << 20
#: Labels up to which they are broadcast to the links (checked by count).
SMALL_LABELS = 200_000


def stars(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every id of the links and the least id it reaches over them."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(ids))
    while True:
        p, q = root[x], root[y]
        apart = p != q
        if not apart.any():
            return ids, ids[root]
        p, q, x, y = p[apart], q[apart], x[apart], y[apart]
        np.minimum.at(root, np.maximum(p, q), np.minimum(p, q))
        up = root[root]
        while (up != root).any():
            root, up = up, up[up]


def _stars_of(batches, most: int):
    held, size = [], 0

    def flush():
        a, b = (np.concatenate(x) for x in zip(*held))
        return pa.RecordBatch.from_arrays([pa.array(x) for x in stars(a, b)], ["id", "root"])

    for batch in batches:
        held.append(tuple(batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1)))
        size += batch.num_rows
        if size > most:
            yield flush()
            held, size = [], 0
    if size:
        yield flush()


def _labels(label: DataFrame) -> DataFrame:
    return F.broadcast(label) if label.count() <= SMALL_LABELS else label


def components(links: DataFrame, name: str = "links", known: DataFrame | None = None, levels: int = 3, most: int = MOST_LINKS) -> DataFrame:
    """(id, component): the least id reachable over ``links(a, b)``, for linked ids only.

    ``known`` holds the components of earlier links: ``links`` then join components,
    and only what they join is worked on. A task turns ``most`` links into stars, ids
    around the least one; ids in several stars link these stars' least ids, whose components
    are found the same way, ``levels`` times, and then by rounds over all that is left.
    Each step is a written table, so lineage stays short and a lost executor costs a
    re-read; an id occurs once a task, so a hub is no large key."""
    pairs = links.select(F.col("a").cast("long"), F.col("b").cast("long"))
    if known is not None:
        small = known.count() <= SMALL_LABELS
        side = F.broadcast(known) if small else known
        for end in ("a", "b"):
            mapped = side.select(F.col("id").alias(end), F.col("component").alias("c"))
            pairs = pairs.join(mapped, end, "left").withColumn(end, F.coalesce("c", end)).select("a", "b")
        if not small:
            pairs = materialize(pairs, f"{name}-joined")
    run = lambda batches: _stars_of(batches, most)
    tasks = -(-links.count() // most) or 1
    held = materialize(pairs.filter("a <> b").coalesce(tasks).mapInArrow(tidy(run), "id long, root long"), f"{name}-stars")
    if known is not None and held.isEmpty():
        return known
    if tasks == 1:
        label = held.withColumnRenamed("root", "component")
        label._prunegraph_path = held._prunegraph_path
    elif levels:
        roots = held.groupBy("id").agg(F.min("root").alias("component"), F.collect_set("root").alias("roots"))
        label = materialize(roots.withColumn("roots", F.when(F.size("roots") > 1, F.col("roots"))), f"{name}-roots")
        meet = label.filter("roots is not null").select(F.explode("roots").alias("a"), F.col("component").alias("b")).filter("a <> b")
        if not meet.isEmpty():
            upper = components(meet, name, None, levels - 1, most)
            above = _labels(upper).select(F.col("id").alias("component"), F.col("component").alias("up"))
            joined = materialize(label.join(above, "component", "left").select("id", F.coalesce("up", "component").alias("component")), f"{name}-label")
            discard(label, upper)
            label = joined
        discard(held)
    else:
        label = _rounds(held, name)
        discard(held)
    if known is not None:
        new = _labels(label)
        moved = known.join(new.select(F.col("id").alias("component"), F.col("component").alias("up")), "component", "left")
        moved = moved.select("id", F.coalesce("up", "component").alias("component"))
        added = label.select("id", "component").join(side.select("id"), "id", "left_anti")
        every = materialize(moved.unionByName(added), f"{name}-label")
        discard(label)
        return every
    found = label.select("id", "component")
    found._prunegraph_path = label._prunegraph_path
    return found


def _rounds(held: DataFrame, name: str) -> DataFrame:
    """(id, component) of ``held(id, root)``: labels go over the links to the least label
    around, then jump to the label of the label, until none changes."""
    both = held.select(F.col("id").alias("a"), F.col("root").alias("b"))
    both = materialize(both.unionByName(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), f"{name}-edges")
    label = materialize(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("component")), f"{name}-label")
    while True:
        near = both.join(label.withColumnRenamed("id", "b"), "b").groupBy(F.col("a").alias("id")).agg(F.min("component").alias("near"))
        step = label.join(near, "id", "left").select("id", F.col("component").alias("old"), F.least("component", F.coalesce("near", "component")).alias("c"))
        heads = label.select(F.col("id").alias("c"), F.col("component").alias("up"))
        moved = step.join(heads, "c", "left").select("id", "old", F.least("c", F.coalesce("up", "c")).alias("component"))
        moved = materialize(moved, f"{name}-label")
        changed = not moved.filter("old <> component").isEmpty()
        discard(label)
        label = moved.select("id", "component")
        label._prunegraph_path = moved._prunegraph_path
        if not changed:
            discard(both)
            return label
