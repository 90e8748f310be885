"""Quality by perplexity under an interpolated modified Kneser-Ney model of bytes.

The model is fitted on the whole of the trusted text. Counts of ``order``-byte strings
are gathered per task and summed over the corpus; continuation counts, discounts,
normalisers and probabilities of all orders are aggregations and joins of count tables
sharded by hash. Every string that occurs in any text gets its probability the same way,
seen in training or not. Scoring reads texts once more: the ``HEAD`` commonest strings
(a fixed number) are broadcast with their probabilities, the others are counted per
document and joined with the sharded table. A document goes if its smoothed perplexity is
above its language's threshold, a quantile over trusted documents kept out of the fit;
smoothing adds ``SMOOTH_BYTES`` of mean text, so that short texts are not judged by chance.

Defined cases: null text is empty; an empty text has perplexity 1 and stays; languages
with fewer than ``LEAST_TRUSTED`` trusted documents (null language included) use the
threshold over all; without any trusted document everything stays; labels without
doc_id or quality are not used, a doc_id with any 0 is not trusted; repeated rows are
scored each; further columns pass through ``select_quality``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prunegraph.llm.common import cleared_after_task, free_name, long_view, materialize, slices, tidied, tidy, utf8  # noqa: F401

ORDER = 5
HEAD = 1 << 19
QUANTILE = 0.995
#: The threshold stands this factor above the quantile, in bits per byte.
MARGIN = 1.05
LEAST_TRUSTED = 40
#: Bytes of a mean text that every perplexity is smoothed with.
SMOOTH_BYTES = 64
#: Trusted rows up to which their ids are broadcast (checked by count).
SMALL_LABELS = 2_000_000
_BLOCK = 1 << 19
#: Different strings a task holds before it passes on their counts.
MOST_HELD = 1 << 20
#: Rows of a batch of partial counts.
_OUT = 1 << 16
_EDGE = 1  # pads the start and closes the end of a text


def packed(raw: np.ndarray, offsets: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """The string of ``order`` bytes that ends at each byte of each padded text, and its row."""
    n = len(offsets) - 1
    gap = order  # order - 1 in front, one behind
    at = np.arange(len(raw)) + np.repeat((np.arange(n) + 1) * gap - 1, np.diff(offsets))
    text = np.full(len(raw) + n * gap + order, _EDGE, np.uint8)
    text[at] = raw
    size = np.diff(offsets) + 1
    first = offsets[:-1] + np.arange(n) * gap
    ends = np.arange(int(size.sum())) + np.repeat(first - np.concatenate([[0], np.cumsum(size)[:-1]]), size)
    g = np.zeros(len(text) - order + 1, np.uint64)
    for k in range(order):
        g = (g << np.uint64(8)) | text[k : len(text) - order + 1 + k]
    return g[ends], np.repeat(np.arange(n), size)


def _merge(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    key = np.concatenate([p[0] for p in parts])
    n = np.concatenate([p[1] for p in parts])
    order = np.argsort(key, kind="stable")
    key, n = key[order], n[order]
    at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    return key[at], np.add.reduceat(n, at) if len(at) else n


def counted(batches, order: int, most: int):
    """Batches (gram, n, t) of partial counts; about ``most`` different strings are held at once."""
    held: list[list] = [[], []]

    def flush():
        keys, counts = zip(*(_merge(h) if h else (np.zeros(0, np.uint64), np.zeros(0, np.int64)) for h in held))
        every, inverse = np.unique(np.concatenate(keys), return_inverse=True)
        n, t = np.zeros(len(every), np.int64), np.zeros(len(every), np.int64)
        np.add.at(n, inverse, np.concatenate(counts))
        t[inverse[len(keys[0]) :]] = counts[1]
        for i in range(0, len(every), _OUT):
            yield pa.RecordBatch.from_arrays([pa.array(long_view(every[i : i + _OUT])), pa.array(n[i : i + _OUT]), pa.array(t[i : i + _OUT])], ["gram", "n", "t"])

    size = 0
    for batch in batches:
        fit = pa.compute.fill_null(batch.column(1), False).to_numpy(zero_copy_only=False)
        for kind in (0, 1):
            raw, offsets = utf8(batch.column(0).filter(pa.array(fit == bool(kind))))
            for a, b in slices(offsets, _BLOCK):
                g, _ = packed(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], order)
                g.sort()
                at = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]]))
                held[kind].append((g[at], np.diff(np.append(at, len(g)))))
                size += len(at)
                if len(held[kind]) >= 16 or size > most:
                    size -= sum(len(k) for k, _ in held[kind])
                    held[kind] = [_merge(held[kind])]
                    size += len(held[kind][0][0])
                if size > most:
                    yield from flush()
                    held, size = [[], []], 0
    if held[0] or held[1]:
        yield from flush()


def string_counts(rows: DataFrame, order: int = ORDER, most: int = MOST_HELD) -> DataFrame:
    """(gram, n, t): occurrences in all texts and in the texts of the fit."""
    run = tidy(lambda batches: counted(batches, order, most))
    return rows.select("text", "fit").mapInArrow(run, "gram long, n long, t long").groupBy("gram").agg(F.sum("n").alias("n"), F.sum("t").alias("t"))


def discounts(counts: dict[int, int]) -> tuple[float, float, float]:
    """The three discounts from how many strings occur once to four times."""
    n1, n2, n3, n4 = (counts.get(k, 0) for k in (1, 2, 3, 4))
    if not n1 or not n2:
        return 0.5, 0.75, 0.9
    y = n1 / (n1 + 2 * n2)
    d = [1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3 if n3 else 1.5]
    return tuple(float(min(max(x, 0.05), k)) for k, x in enumerate(d, start=1))


def _discount(c: Column, d: tuple[float, float, float]) -> Column:
    return F.when(c == 1, d[0]).when(c == 2, d[1]).otherwise(d[2])


def _suffix(gram: str, order: int) -> Column:
    return F.col(gram).bitwiseAND((1 << (8 * (order - 1))) - 1)


def probabilities(counts: DataFrame, order: int = ORDER) -> DataFrame:
    """(gram, n, logp): the model's log probability of every string that occurs."""
    # count tables per order: strings of the fit, then distinct left extensions
    level = {order: counts.filter("t > 0").select("gram", F.col("t").alias("c"))}
    for k in range(order - 1, 0, -1):
        level[k] = level[k + 1].groupBy(_suffix("gram", k + 1).alias("gram")).agg(F.count(F.lit(1)).alias("c"))
    wanted = {order: counts.select("gram")}
    for k in range(order - 1, 0, -1):
        wanted[k] = wanted[k + 1].select(_suffix("gram", k + 1).alias("gram")).distinct()
    previous = None
    for k in range(1, order + 1):
        c = materialize(level[k], f"counts-{k}") if k < order else level[k]
        few = {r["c"]: r["n"] for r in c.filter("c <= 4").groupBy("c").agg(F.count(F.lit(1)).alias("n")).collect()}
        d = discounts(few)
        context = c.groupBy(F.shiftright("gram", 8).alias("context")).agg(
            F.sum("c").alias("total"), F.sum(_discount(F.col("c"), d)).alias("freed")
        )
        want = wanted[k].withColumn("context", F.shiftright("gram", 8)).withColumn("lower", _suffix("gram", k))
        with_context = want.join(context, "context", "left").join(c, "gram", "left")
        if previous is None:
            lower = with_context.withColumn("p_lower", F.lit(1.0 / 256))
        else:
            lower = with_context.join(previous.select(F.col("gram").alias("lower"), F.col("p").alias("p_lower")), "lower", "left")
        own = F.coalesce((F.col("c") - _discount(F.col("c"), d)) / F.col("total"), F.lit(0.0))
        left = F.coalesce(F.col("freed") / F.col("total"), F.lit(1.0))
        previous = materialize(lower.select("gram", (own + left * F.col("p_lower")).alias("p")), f"p-{k}")
        level[k] = c
    return previous.join(counts.select("gram", "n"), "gram").select("gram", "n", F.log("p").alias("logp"))


class StringTable:
    """Hash table over at most ``HEAD`` strings; misses are found exactly."""

    def __init__(self, keys: np.ndarray, values: np.ndarray, bits: int = 21):
        self.shift, size = np.uint64(64 - bits), 1 << bits
        self.keys, self.values = np.full(size, np.iinfo(np.uint64).max, np.uint64), np.zeros(size, np.float32)
        slot = self._slot(keys)
        self.keys[slot], self.values[slot] = keys, values  # the last of a slot wins
        rest = self.keys[slot] != keys
        order = np.argsort(keys[rest])
        self.more, self.more_values = keys[rest][order], values[rest][order]

    def _slot(self, g: np.ndarray) -> np.ndarray:
        return ((g * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).view(np.int64)

    def get(self, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Values (0 where missing) and the positions of missing strings."""
        slot = self._slot(g)
        out = self.values[slot]
        miss = np.flatnonzero(self.keys[slot] != g)
        out[miss] = 0
        if len(miss) and len(self.more):
            k = np.minimum(np.searchsorted(self.more, g[miss]), len(self.more) - 1)
            hit = self.more[k] == g[miss]
            out[miss[hit]] = self.more_values[k[hit]]
            miss = miss[~hit]
        return out, miss


def scores(rows: DataFrame, probability: DataFrame, order: int = ORDER, head: int = HEAD) -> DataFrame:
    """``rows`` without text, plus n_bytes and log_likelihood; rows of one "key" must have one text."""
    spark = rows.sparkSession
    # a fixed number of strings, the commonest
    top = probability.orderBy(F.desc("n"), "gram").limit(head).select("gram", F.col("logp").cast("float")).toArrow()
    shared = spark.sparkContext.broadcast((top.column(0).to_numpy().view(np.uint64), top.column(1).to_numpy()))
    rest_columns = [c for c in rows.columns if c != "text"]

    def run(batches):
        table = _table_of(shared)
        for batch in batches:
            raw, offsets = utf8(batch.column(0))
            for a, b in slices(offsets, _BLOCK):
                g, row = packed(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], order)
                value, miss = table.get(g)
                total = np.bincount(row, value, b - a)
                cut = np.searchsorted(row[miss], np.arange(b - a + 1)).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(cut), pa.array(long_view(g[miss])))
                yield pa.RecordBatch.from_arrays([*(c.slice(a, b - a) for c in batch.columns[1:]), pa.array(np.diff(offsets[a : b + 1])), pa.array(total), lists], [*rest_columns, "n_bytes", "head_sum", "rare"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*rest_columns).schema.fields)
    scored = materialize(rows.select("text", *rest_columns).mapInArrow(tidy(run), f"{schema}, n_bytes long, head_sum double, rare array<long>"), "scored")
    rare = scored.filter(F.size("rare") > 0).select("key", F.explode("rare").alias("gram")).groupBy("key", "gram").agg(F.count(F.lit(1)).alias("m"))
    tail = rare.join(probability.select("gram", "logp"), "gram").groupBy("key").agg(F.sum(F.col("m") * F.col("logp")).alias("tail_sum"))
    # m counts the strings of all rows of a key, which hold the same text
    copies = scored.groupBy("key").agg(F.count(F.lit(1)).alias("n_rows")).filter("n_rows > 1")
    tail = tail.join(copies, "key", "left").select("key", (F.col("tail_sum") / F.coalesce("n_rows", F.lit(1))).alias("tail_sum"))
    return scored.drop("rare").join(tail, "key", "left").withColumn("log_likelihood", F.col("head_sum") + F.coalesce("tail_sum", F.lit(0.0))).drop("head_sum", "tail_sum")


_tables: dict = {}
cleared_after_task(_tables.clear)


def _table_of(shared) -> StringTable:
    """One table per task and broadcast."""
    keys, values = shared.value
    if _tables.get("of") is not keys:
        _tables.update(of=keys, table=StringTable(keys, values))
    return _tables["table"]


def trusted(labels: DataFrame) -> DataFrame:
    """doc_id of trusted documents and whether they are in the fit (three of four)."""
    good = labels.filter("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("q")).filter("q = 1")
    return good.select("doc_id", (F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(4)) != 0).alias("fit"))


def score_quality(docs: DataFrame, labels: DataFrame, order: int = ORDER, quantile: float = QUANTILE) -> DataFrame:
    """Per row: doc_id, lang, key, n_bytes, log_likelihood, perplexity, smoothed_perplexity,
    threshold, kept; a text with bytes is kept if the smoothed value is within the threshold."""
    marks = materialize(trusted(labels), "trusted")
    side = F.broadcast(marks) if marks.count() <= SMALL_LABELS else marks
    rows = docs.select(F.col("doc_id").cast("long"), "text", F.col("lang").cast("string")).join(side, "doc_id", "left").withColumn("key", F.xxhash64("doc_id", "text", "lang"))
    counts = materialize(string_counts(rows, order), "strings")
    probability = materialize(probabilities(counts, order), "probability")
    found = scores(rows, probability, order)
    mean = found.filter("fit is not null").agg(F.sum("log_likelihood") / F.sum(F.col("n_bytes") + 1)).first()[0]
    mean = -2.0 if mean is None else mean
    bits = -(F.col("log_likelihood") + SMOOTH_BYTES * mean) / (F.col("n_bytes") + 1 + SMOOTH_BYTES)
    found = materialize(found.withColumn("smoothed", bits), "quality-scores")
    held = found.filter("fit = false")
    q = lambda: F.percentile_approx("smoothed", quantile, 100_000)
    by_lang = held.filter("lang is not null").groupBy("lang").agg(q().alias("own"), F.count(F.lit(1)).alias("n")).filter(F.col("n") >= LEAST_TRUSTED).select("lang", "own")
    every = held.agg(q().alias("all"))
    limits = found.join(by_lang, "lang", "left").crossJoin(F.broadcast(every))  # one row
    threshold = F.coalesce("own", "all") * MARGIN
    return limits.select(
        "doc_id", "lang", "key", "n_bytes", "log_likelihood",
        F.when(F.col("n_bytes") == 0, 1.0).otherwise(F.exp(-F.col("log_likelihood") / (F.col("n_bytes") + 1))).alias("perplexity"),
        F.exp("smoothed").alias("smoothed_perplexity"),
        F.exp(threshold).alias("threshold"),
        (F.col("n_bytes").eqNullSafe(0) | F.coalesce(F.exp("smoothed") <= F.exp(threshold), F.lit(True))).alias("kept"),
    )


def select_quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, all their columns."""
    name = free_name(docs, "rejected_key")
    found = score_quality(docs, labels).filter("not kept").select(F.col("key").alias(name)).distinct()
    bad = materialize(found, "rejected")
    side = F.broadcast(bad) if bad.count() <= SMALL_LABELS else bad
    key = F.xxhash64(docs["doc_id"].cast("long"), docs["text"], docs["lang"].cast("string"))
    return docs.join(side, key == side[name], "left_anti")
