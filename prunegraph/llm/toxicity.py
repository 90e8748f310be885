"""Toxicity: a linear classifier on character n-grams scaled by log-count ratios.

A feature is the presence of a character n-gram of the lower-cased text. Its value is
its naive Bayes log-count ratio between the two classes, and a logistic regression on
the values gives the score. n-grams whose ratio lies within ``least_z`` standard errors
of zero carry no evidence and are left out.

The classifier is fitted on at most ``MOST_LABELLED`` labelled rows, those with the
least hash of doc_id, and keeps the ``MOST_FEATURES`` n-grams of most evidence; a toxic
row, the rarer kind, weighs ``POSITIVE`` times. Every text is scored whole.

Defined cases: null text is empty; an empty or featureless text has the score of the
intercept; without labels of both classes the score is the share of the class seen (0
without labels); labels that are null are not used; of several labels of one doc_id the
largest holds; repeated rows are scored each; a row without doc_id is scored and not
held out; further columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prunegraph.llm.common import crc32, discard, long_view, materialize, mix

ORDERS = (4, 5, 6)
MOST_LABELLED = 12_000
MOST_FEATURES = 20_000
LEAST_Z = 2.3
POSITIVE = 4.0
BLOCK_CHARS = 1 << 19
_BASE = np.uint64(0x9E3779B97F4A7C15)


@dataclass
class ToxicityModel:
    keys: np.ndarray  # sorted uint64 n-gram hashes
    weights: np.ndarray  # one weight per key, ratio included
    intercept: float


def _grams(texts: list[str], orders=ORDERS):
    """(row of each character, then per order the hash of the n-gram that starts there)."""
    lowered = [t.lower() for t in texts]
    code = np.frombuffer("\0".join(lowered).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    lengths = np.fromiter(map(len, lowered), np.int64, len(lowered)) + 1
    ends = np.cumsum(lengths) - 1
    row = np.repeat(np.arange(len(texts), dtype=np.int32), lengths)[: len(code)]
    h, made = code + np.uint64(1), []
    for n in range(2, max(orders) + 1):
        h = h[:-1] * _BASE + code[n - 1 :] if len(h) > 1 else h[:0]
        if n in orders:
            made.append((n, h ^ (h >> np.uint64(29))))
    return row, ends, made


def _blocks(texts: list[str]):
    at, held = 0, 0
    for i, t in enumerate(texts):
        if i > at and held + len(t) > BLOCK_CHARS:
            yield at, i
            at, held = i, 0
        held += len(t)
    if at < len(texts):
        yield at, len(texts)


def _distinct(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (row, n-gram hash) pairs of a block."""
    row, ends, made = _grams(texts)
    rows, keys = [], []
    for n, h in made:
        inside = ends[row[: len(h)]] - np.arange(len(h)) >= n
        rows.append(row[: len(h)][inside])
        keys.append(h[inside])
    rows, keys = np.concatenate(rows), np.concatenate(keys)
    order = np.lexsort((keys, rows))
    rows, keys = rows[order], keys[order]
    first = np.ones(len(keys), bool)
    first[1:] = (keys[1:] != keys[:-1]) | (rows[1:] != rows[:-1])
    return rows[first], keys[first]


class Lookup:
    """Sorted keys behind a bit table, so that most n-grams cost one small read."""

    def __init__(self, keys: np.ndarray, bits: int = 22):
        self.keys, self.shift = keys, np.uint64(64 - bits)
        self.maybe = np.zeros(1 << bits, bool)
        self.maybe[self._slot(keys)] = True

    def _slot(self, h: np.ndarray) -> np.ndarray:
        return ((h * np.uint64(0xD6E8FEB86659FD93)) >> self.shift).view(np.int64)

    def hits(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions in ``h`` that hold a key, and the key's index."""
        at = np.flatnonzero(self.maybe[self._slot(h)])
        if not len(self.keys) or not len(at):
            return at[:0], at[:0]
        k = np.minimum(np.searchsorted(self.keys, h[at]), len(self.keys) - 1)
        same = self.keys[k] == h[at]
        return at[same], k[same]

    def present(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Distinct (row, key index) pairs of a block."""
        row, _, made = _grams(texts)
        pairs = [np.zeros(0, np.int64)]
        for _, h in made:
            at, k = self.hits(h)
            pairs.append(row[at].astype(np.int64) * len(self.keys) + k)
        pairs = np.unique(np.concatenate(pairs))
        return pairs // max(1, len(self.keys)), pairs % max(1, len(self.keys))


def fit(labelled: DataFrame, seed: int = 5) -> ToxicityModel:
    """``labelled`` (key, text, toxic), bounded by the caller; a materialised one is best."""
    spark = labelled.sparkSession

    def count(batches):
        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            toxic = batch.column("toxic").to_numpy(zero_copy_only=False)
            for a, b in _blocks(texts):
                rows, keys = _distinct(texts[a:b])
                found, inverse = np.unique(keys, return_inverse=True)
                all_n = np.bincount(inverse, minlength=len(found))
                bad_n = np.bincount(inverse, weights=toxic[a:b][rows], minlength=len(found)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(long_view(found)), pa.array(bad_n), pa.array(all_n - bad_n)], ["key", "p", "q"])

    sizes = labelled.agg(F.sum("toxic"), F.count(F.lit(1))).first()
    n_p, n_all = int(sizes[0] or 0), int(sizes[1])
    if not 0 < n_p < n_all:
        share = n_p / n_all if n_all else 0.0
        return ToxicityModel(np.zeros(0, np.uint64), np.zeros(0), float(np.log((share + 1e-6) / (1 - share + 1e-6))))
    half = F.lit(0.5)
    ratio = F.log((F.col("p") + half) / (n_p + 1.0)) - F.log((F.col("q") + half) / (n_all - n_p + 1.0))
    z = ratio / F.sqrt(1 / (F.col("p") + half) + 1 / (F.col("q") + half))
    counted = labelled.mapInArrow(count, "key long, p long, q long").groupBy("key").agg(F.sum("p").alias("p"), F.sum("q").alias("q"))
    # bounded by MOST_FEATURES
    top = counted.filter("p + q >= 3").select("key", ratio.alias("ratio"), F.abs(z).alias("z")).filter(F.col("z") >= LEAST_Z).orderBy(F.desc("z"), "key").limit(MOST_FEATURES).collect()
    keys = np.array([r["key"] for r in top], np.int64).view(np.uint64)
    order = np.argsort(keys)
    keys, ratio = keys[order], np.array([r["ratio"] for r in top])[order]
    shared = spark.sparkContext.broadcast(keys)

    def present(batches):
        lookup = Lookup(shared.value)
        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            toxic = batch.column("toxic").to_numpy(zero_copy_only=False).astype(np.int32)
            for a, b in _blocks(texts):
                rows, ks = lookup.present(texts[a:b])
                cut = np.searchsorted(rows, np.arange(b - a + 1))
                lists = pa.ListArray.from_arrays(pa.array(cut, pa.int32()), pa.array(ks, pa.int32()))
                yield pa.RecordBatch.from_arrays([pa.array(toxic[a:b]), lists], ["toxic", "features"])

    # at most most_labelled rows, each a list of selected features
    rows = labelled.select("text", "toxic").mapInArrow(present, "toxic int, features array<int>").toArrow()
    y = rows.column("toxic").to_numpy().astype(float)
    lists = rows.column("features").combine_chunks()
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    where = np.repeat(np.arange(len(y)), pa.compute.list_value_length(lists).to_numpy(zero_copy_only=False))
    weights, intercept = _logistic(where, flat, np.clip(ratio, -6, 6), y)
    return ToxicityModel(keys, weights * np.clip(ratio, -6, 6), intercept)


def _logistic(row: np.ndarray, feature: np.ndarray, value: np.ndarray, y: np.ndarray, penalty: float = 0.5, rounds: int = 400, positive: float = POSITIVE) -> tuple[np.ndarray, float]:
    """Penalised logistic regression on sparse presence rows (accelerated gradient).

    A toxic row counts ``positive`` times."""
    n, p = len(y), len(value)
    v = value[feature]
    w, b, w0, b0, t = np.zeros(p), 0.0, np.zeros(p), 0.0, 1.0
    share = y.mean()
    b = b0 = float(np.log(share / (1 - share)))
    # step from a bound on the curvature, found by a few power steps
    u = np.ones(p + 1)
    for _ in range(12):
        z = np.bincount(row, v * u[feature], n) + u[p]
        u = np.append(np.bincount(feature, v * z[row], p), z.sum())
        top = np.linalg.norm(u)
        u = u / max(top, 1e-12)
    step = 1 / (0.25 * positive * top + penalty)
    for _ in range(rounds):
        s = 1 / (1 + np.exp(-np.clip(np.bincount(row, v * w0[feature], n) + b0, -30, 30)))
        g = (s - y) * np.where(y > 0, positive, 1.0)
        w1 = w0 - step * (np.bincount(feature, v * g[row], p) + penalty * w0)
        b1 = b0 - step * g.sum()
        t1 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        w0, b0 = w1 + (t - 1) / t1 * (w1 - w), b1 + (t - 1) / t1 * (b1 - b)
        w, b, t = w1, b1, t1
    return w, float(b)


def score(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """doc_id and score of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        lookup = Lookup(m.keys)
        for batch in batches:
            texts = batch.column(1)
            for at in range(0, batch.num_rows, 512):
                some = [t or "" for t in texts.slice(at, 512).to_pylist()]
                z = np.full(len(some), m.intercept)
                for a, b in _blocks(some):
                    rows, ks = lookup.present(some[a:b])
                    z[a:b] += np.bincount(rows, m.weights[ks] if len(ks) else None, b - a)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 512), pa.array(1 / (1 + np.exp(-np.clip(z, -40, 40))))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, score double")


def labelled_rows(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED) -> DataFrame:
    """At most ``most`` labelled texts outside the held-out fold."""
    chosen = (
        labels.filter("toxic is not null and doc_id is not null")
        .filter(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 != 1)
        .groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").cast("int").alias("toxic"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    )
    # at most ``most`` ids, one row of each
    return docs.select(F.col("doc_id").cast("long"), "text").join(F.broadcast(chosen), "doc_id").dropDuplicates(["doc_id"]).select("text", "toxic")


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    train = materialize(labelled_rows(docs, labels), "toxic-train")
    model = fit(train)
    discard(train)
    return score(docs, model).select(
        "doc_id",
        F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= threshold).cast("int").alias("predicted"),
    )
