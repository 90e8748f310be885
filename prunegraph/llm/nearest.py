"""Approximate nearest neighbours by multiprobe p-stable hashing.

Vectors are scaled to unit length, where Euclidean order is cosine order. Each hash
table joins ``projections`` Gaussian projections, shifted and cut into cells. A query
visits its own bucket and perturbed ones in the order of their estimated success: the
probability, under the tables' Gaussian, that a neighbour at the distance of the k-th
one lies there. It stops where the buckets visited in all tables together reach the
expected recall ``target``. Candidates of all tables are merged and ranked by exact
cosine in double precision.

Parameters follow the data. The distance of the k-th neighbour comes from an audit: a
bounded sample of queries compared with every row. The number of projections grows with
the logarithm of the number of vectors, so buckets stay small. The same sample measures
recall; below ``RECALL`` the tables are doubled, and at last all is compared.

Equal vectors are indexed once with their least ids, enough for every rank asked for.
A table's buckets are dealt into groups by the first cells of their key; groups above
``block`` vectors are split into blocks that all see the group's queries.

Defined cases: see ``vectors.clean`` for vectors left out; vectors of different lengths
never meet; a query with fewer than ``k`` candidates found is compared with the whole
table; ties go to the smaller id; a repeated vec_id is one vector per distinct content;
empty tables give no rows; further columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.llm.common import discard, materialize
from prunegraph.llm.vectors import clean, collapse, lists, matrix

TABLES, MOST_TABLES = 8, 32
TARGET, RECALL = 0.89, 0.9
#: Queries of the audit.
AUDIT = 64
#: Vectors that one task holds.
BLOCK = 32_768
#: Buckets of one table that a query looks at most.
MOST_PROBES = 4096
_STEPS = np.array([0, -1, 1, -2, 2])
_LEAD = 3  # cells of a key that choose its group
_BINS = 256


class Hashing:
    """One hash table's projections for vectors of one length."""

    def __init__(self, dim: int, table: int, projections: int, cell: float, seed: int):
        rng = np.random.default_rng([seed, table, dim])
        self.cell = cell
        self.lines = rng.standard_normal((dim, projections)) / cell
        self.shift = rng.random(projections)
        self.mixed = rng.integers(1, 1 << 62, projections) | 1

    def cells(self, x: np.ndarray) -> np.ndarray:
        """Projections of unit vectors, in cells."""
        return x @ self.lines + self.shift

    def keys(self, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(key of the bucket, key of its leading cells) of whole cells."""
        own = own.astype(np.int64)
        lead = min(_LEAD, own.shape[1])
        return (own * self.mixed).sum(axis=1), (own[:, :lead] * self.mixed[:lead]).sum(axis=1)

    def probes(self, x: np.ndarray, reach: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(probability, key, leading key) of the likeliest buckets of each row, best first.

        A step of a coordinate has the Gaussian mass of its cell; the best steps of either
        half of the coordinates are joined."""
        f = self.cells(x)
        own = np.floor(f).astype(np.int64)
        low = f - own
        n, k = low.shape
        edges = (np.arange(-2, 4)[None, None] - low[:, :, None]) * self.cell / reach
        mass = np.diff(_normal(edges), axis=2)  # cells -2 .. 2
        logp = np.log(np.maximum(mass, 1e-30))[:, :, _STEPS + 2]
        halves = []
        for at in (np.arange(k // 2), np.arange(k // 2, k)):
            halves.append(self._best(logp[:, at], at))
        (p, key, lead), (q, other, more) = halves
        total = (p[:, :, None] + q[:, None, :]).reshape(n, -1)
        m = min(MOST_PROBES, total.shape[1])
        order = np.argpartition(-total, m - 1, axis=1)[:, :m]
        i, j = order // q.shape[1], order % q.shape[1]
        pick = np.take_along_axis
        base, base_lead = self.keys(own)
        return np.exp(pick(total, order, 1)), base[:, None] + pick(key, i, 1) + pick(other, j, 1), base_lead[:, None] + pick(lead, i, 1) + pick(more, j, 1)

    def _best(self, logp: np.ndarray, at: np.ndarray, most: int = 128):
        """The likeliest joint steps of the coordinates ``at``, added one at a time."""
        n = len(logp)
        p, key, lead = np.zeros((n, 1)), np.zeros((n, 1), np.int64), np.zeros((n, 1), np.int64)
        for c, k in enumerate(at):
            p = (p[:, :, None] + logp[:, c][:, None, :]).reshape(n, -1)
            move = _STEPS * self.mixed[k]
            key = (key[:, :, None] + move).reshape(n, -1)
            lead = (lead[:, :, None] + (move if k < _LEAD else 0 * move)).reshape(n, -1)
            if p.shape[1] > most:
                order = np.argpartition(-p, most - 1, axis=1)[:, :most]
                p, key, lead = (np.take_along_axis(a, order, 1) for a in (p, key, lead))
        return p, key, lead


def _normal(z: np.ndarray) -> np.ndarray:
    """Distribution function of the normal law (a public rational approximation of erf)."""
    x = np.abs(z) / math.sqrt(2)
    t = 1 / (1 + 0.3275911 * x)
    tail = ((((1.061405429 * t - 1.453152027) * t + 1.421413741) * t - 0.284496736) * t + 0.254829592) * t * np.exp(-x * x)
    return np.where(z >= 0, 1 - tail / 2, tail / 2)


def projections_for(n: int) -> int:
    """Projections of a key for ``n`` vectors: 8 at fifty thousand, 16 from a hundred million on."""
    return int(np.clip(round(0.75 * math.log2(max(2, n)) - 3.7), 4, 16))


def _by_length(batch, at: int):
    """Row numbers and matrix for every vector length in a batch."""
    sizes = pa.compute.list_value_length(batch.column(at)).to_numpy(zero_copy_only=False)
    for d in np.unique(sizes):
        rows = np.flatnonzero(sizes == d)
        yield rows, matrix(batch.column(at).take(pa.array(rows)))


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _placed(once: DataFrame, tables: int, projections: int, cell: float, groups: int, seed: int) -> DataFrame:
    """Every vector in its bucket of every table: (tab, part, bucket, rep, unit)."""

    def run(batches):
        for batch in batches:
            for rows, x in _by_length(batch, 1):
                unit, rep = _unit(x), batch.column(0).take(pa.array(rows))
                short = lists(unit.astype(np.float32), pa.float32())
                for t in range(tables):
                    h = Hashing(x.shape[1], t, projections, cell, seed)
                    key, lead = h.keys(np.floor(h.cells(unit)))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), t, np.int32)), pa.array(np.full(len(x), x.shape[1], np.int32)), pa.array(_part(lead, groups)), pa.array(key), rep, short], ["tab", "dim", "part", "bucket", "rep", "unit"])

    return once.select("rep", "vector").mapInArrow(run, "tab int, dim int, part int, bucket long, rep long, unit array<float>")


def _part(lead: np.ndarray, groups: int) -> np.ndarray:
    spread = lead.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return ((spread >> np.uint64(33)) % np.uint64(groups)).astype(np.int32)


def _probed(asked: DataFrame, tables: int, projections: int, cell: float, reach: float, target: float, groups: int, seed: int) -> DataFrame:
    """The buckets each query visits: (tab, dim, part, query_id, unit, keys)."""

    def run(batches):
        for batch in batches:
            for rows, x in _by_length(batch, 1):
                hashes = [Hashing(x.shape[1], t, projections, cell, seed) for t in range(tables)]
                for at in range(0, len(x), 64):
                    yield from some(batch.column(0).take(pa.array(rows[at : at + 64])), _unit(x[at : at + 64]), hashes)

    def some(ids, unit, hashes):
        n = len(unit)
        found = [h.probes(unit, reach) for h in hashes]
        # success of all visited buckets by falling probability: one bin is a factor of e^(1/8)
        bins, won = [], np.ones((n, _BINS))
        for p, _, _ in found:
            b = np.minimum((-8 * np.log(np.maximum(p, 1e-30))).astype(np.int64), _BINS - 1)
            mass = np.bincount((np.arange(n)[:, None] * _BINS + b).ravel(), p.ravel(), n * _BINS).reshape(n, _BINS)
            won *= 1 - np.minimum(np.cumsum(mass, axis=1), 1)
            bins.append(b)
        enough = 1 - won >= target
        last = np.where(enough.any(axis=1), enough.argmax(axis=1), _BINS - 1)
        short = unit.astype(np.float32)
        for t, ((_, key, lead), b) in enumerate(zip(found, bins)):
            q, j = np.nonzero(b <= last[:, None])
            part, key = _part(lead[q, j], groups), key[q, j]
            order = np.lexsort((part, q))
            q, part, key = q[order], part[order], key[order]
            first = np.flatnonzero(np.concatenate([[True], (q[1:] != q[:-1]) | (part[1:] != part[:-1])]))
            m = len(first)
            keys = pa.ListArray.from_arrays(pa.array(np.append(first, len(key)).astype(np.int32)), pa.array(key))
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(m, t, np.int32)), pa.array(np.full(m, unit.shape[1], np.int32)), pa.array(part[first]), ids.take(pa.array(q[first])), lists(short[q[first]], pa.float32()), keys],
                ["tab", "dim", "part", "query_id", "unit", "keys"],
            )

    return asked.select("query_id", "vector").repartition("query_id").mapInArrow(run, "tab int, dim int, part int, query_id long, unit array<float>, keys array<long>")


_RANKED = "query_id long, rep long, score double, met long"


def _best(score: np.ndarray, rep: np.ndarray, keep: int) -> np.ndarray:
    """Positions of the ``keep`` best, ties to the smaller representative."""
    if len(score) > keep:
        at = np.flatnonzero(score >= np.partition(score, len(score) - keep)[len(score) - keep])
    else:
        at = np.arange(len(score))
    return at[np.lexsort((rep[at], -score[at]))][:keep]


def _ranked(ids, reps, scores, met):
    cat = lambda parts, kind: pa.array(np.concatenate(parts) if parts else np.zeros(0), kind)
    return pa.table([cat(ids, pa.int64()), cat(reps, pa.int64()), cat(scores, pa.float64()), cat(met, pa.int64())], ["query_id", "rep", "score", "met"])


def _rank_buckets(index: DataFrame, asked: DataFrame, keep: int) -> DataFrame:
    """The ``keep`` best of each query among the buckets it visits in a block; ``met``, on
    the first row of a query, is how many vectors it was compared with."""

    def rank(key, left, right):
        ids, reps, scores, met = [], [], [], []
        if left.num_rows and right.num_rows:
            bucket = left.column("bucket").to_numpy()
            order = np.argsort(bucket)
            bucket, rep, x = bucket[order], left.column("rep").to_numpy()[order], matrix(left.column("unit"), np.float32)[order]
            q, names = matrix(right.column("unit"), np.float32), right.column("query_id").to_numpy()
            keys = right.column("keys").combine_chunks()
            at, flat = keys.offsets.to_numpy(), keys.values.to_numpy()
            for i in range(len(q)):
                own = flat[at[i] : at[i + 1]]
                low, high = np.searchsorted(bucket, own, "left"), np.searchsorted(bucket, own, "right")
                size = high - low
                n = int(size.sum())
                if not n:
                    continue
                rows = np.arange(n) + np.repeat(low - (np.cumsum(size) - size), size)
                score = x[rows] @ q[i]
                best = _best(score, rep[rows], keep)
                ids.append(np.full(len(best), names[i]))
                reps.append(rep[rows[best]])
                scores.append(score[best].astype(np.float64))
                met.append(np.concatenate([[n], np.zeros(len(best) - 1, np.int64)]))
        return _ranked(ids, reps, scores, met)

    on = ["tab", "dim", "part", "block"]
    return index.groupBy(*on).cogroup(asked.groupBy(*on)).applyInArrow(rank, _RANKED)


def _compare(once: DataFrame, asked: DataFrame, keep: int, block: int) -> DataFrame:
    """Queries against every row of their length, in blocks of rows."""
    counts = once.groupBy(F.size("vector").alias("dim")).agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))
    counts = F.broadcast(counts)  # a row per vector length
    rows = once.withColumn("dim", F.size("vector")).join(counts, "dim").withColumn("block", F.pmod(F.xxhash64("rep", F.lit(7)), F.col("blocks")).cast("int"))
    sent = asked.withColumn("dim", F.size("vector")).join(counts, "dim").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))

    def rank(key, left, right):
        ids, reps, scores, met = [], [], [], []
        if left.num_rows and right.num_rows:
            x, rep = _unit(matrix(left.column("vector"))), left.column("rep").to_numpy()
            q, names = _unit(matrix(right.column("vector"))), right.column("query_id").to_numpy()
            for at in range(0, len(q), 256):
                for name, score in zip(names[at : at + 256], q[at : at + 256] @ x.T):
                    best = _best(score, rep, keep)
                    ids.append(np.full(len(best), name))
                    reps.append(rep[best])
                    scores.append(score[best])
                    met.append(np.concatenate([[len(x)], np.zeros(len(best) - 1, np.int64)]))
        return _ranked(ids, reps, scores, met)

    on = ["dim", "block"]
    return rows.select("dim", "block", "rep", "vector").groupBy(*on).cogroup(sent.select("dim", "block", "query_id", "vector").groupBy(*on)).applyInArrow(rank, _RANKED)


def _nearest(found: DataFrame, once: DataFrame, asked: DataFrame, k: int) -> DataFrame:
    """query_id, rank, vec_id, score: candidates of all tables merged, scored exactly."""
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "rep")
    merged = found.groupBy("query_id", "rep").agg(F.max("score").alias("score"))
    # float32 orders what lies more than its rounding apart; a few more are scored exactly
    few = merged.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= 2 * k + 3).select("query_id", "rep")
    pairs = few.join(once.select("rep", "vector", "ids"), "rep").join(asked.select("query_id", F.col("vector").alias("asked")), "query_id")

    def exact(batches):
        for batch in batches:
            x, q = (batch.column(i).to_pylist() for i in (2, 3))
            score = [float(np.dot(a, b) / (np.linalg.norm(a) * np.linalg.norm(b))) for a, b in zip(map(np.array, x), map(np.array, q))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score, pa.float64())], ["query_id", "ids", "score"])

    scored = pairs.select("query_id", "ids", "vector", "asked").mapInArrow(exact, "query_id long, ids array<long>, score double")
    each = scored.select("query_id", "score", F.explode("ids").alias("vec_id")).filter("vec_id <> query_id")
    each = each.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return each.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def search(vectors: DataFrame, queries, k: int = 5, tables: int = TABLES, target: float = TARGET, block: int = BLOCK, seed: int = 17, report: dict | None = None) -> DataFrame:
    """query_id, rank, vec_id, score for the rows of ``vectors`` that ``queries`` selects.

    ``report`` receives the audit: recall, reach, tables, projections and ``met``, the
    share of the table a query was compared with (each table's visit counts)."""
    rows = clean(vectors)
    report = {} if report is None else report
    once = materialize(collapse(rows, [], k + 1), "distinct-vectors")
    asked = materialize(rows.filter(queries).select(F.col("vec_id").cast("long").alias("query_id"), "vector").distinct(), "queries")
    n, n_asked = once.count(), asked.count()
    sample = materialize(asked.orderBy(F.xxhash64("query_id"), "query_id").limit(AUDIT), "audit")
    truth = materialize(_nearest(_compare(once, sample, k + 1, block), once, sample, k), "audit-truth")
    far = truth.filter(F.col("rank") == k).agg(F.percentile_approx("score", 0.5)).first()[0]
    reach = math.sqrt(max(1e-4, 2 - 2 * far)) if far is not None else 1.0
    projections, groups = projections_for(n), max(1, -(-n // block))
    cell = 1.17 * reach
    while True:
        placed = materialize(_placed(once, tables, projections, cell, groups, seed), "buckets")
        sizes = placed.groupBy("tab", "dim", "part").agg(F.ceil(F.count(F.lit(1)) / (2 * block)).cast("int").alias("blocks"))
        sizes = materialize(sizes, "bucket-sizes")
        on = ["tab", "dim", "part"]
        index = placed.join(sizes, on).withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")).drop("blocks")
        probed = _probed(asked, tables, projections, cell, reach, target, groups, seed).join(sizes, on)
        probed = probed.withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("blocks")
        found = materialize(_rank_buckets(index, probed, k + 1), "candidates")
        best = materialize(_nearest(found, once, asked, k), "nearest")
        all_ = truth.count()
        recall = best.join(truth, ["query_id", "vec_id"], "left_semi").count() / all_ if all_ else 1.0
        met = found.agg(F.sum("met")).first()[0] or 0
        report.update(recall=recall, reach=reach, tables=tables, projections=projections, met=met / max(1, n * n_asked))
        discard(placed, sizes, found)
        if recall >= RECALL:
            break
        if tables >= MOST_TABLES:
            return _nearest(_compare(once, asked, k + 1, block), once, asked, k)
        tables, target = 2 * tables, (1 + target) / 2
    few = best.groupBy("query_id").count().filter(F.col("count") >= k).select("query_id")
    short = materialize(asked.join(few, "query_id", "left_anti"), "short-queries")
    if short.isEmpty():
        return best
    return best.join(short, "query_id", "left_anti").unionByName(_nearest(_compare(once, short, k + 1, block), once, short, k))
