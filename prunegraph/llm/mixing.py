"""Mixing sources: temperature weights realised as budgeted block permutations.

A source's share of tokens p becomes the weight p^a / sum p^a. The exponent a in [0, 1]
is bisected: either to the largest one whose weights keep a target entropy, or to the
smallest one for which no source is repeated more than ``most_repeats`` times within
the budget. Each source then has budget * weight tokens. A source is cut into blocks of
about ``block_tokens`` tokens by a hash of its rows; every epoch reads the blocks in an
order of its own, and the last, partial epoch stops inside the block that the budget
ends in, so the realised tokens of a source differ from its budget by less than a row.

Blocks of a source are ranked, and their tokens summed, in two steps: over buckets of
the order's hash, then inside a bucket, so that no task holds all blocks of a source.
Up to ``FEW_SOURCES`` sources the exponent is bisected over a list of their totals; beyond
it each step of the bisection is an aggregation over the table of totals.

Tokens are UTF-8 bytes divided by ``BYTES_PER_TOKEN``, one at least.

Defined cases: a null source is a source of its own; null and empty texts have one
token; repeated rows are rows, spread over blocks by a number of the row; ties in an
order are broken by doc_id; with one source the weight is 1; empty tables give no rows;
further columns are kept by ``mixed_documents``.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.llm.common import free_name, materialize, with_copy

BYTES_PER_TOKEN = 4
BLOCK_TOKENS = 200_000
#: Sources whose totals are bisected as a list.
FEW_SOURCES = 100_000
#: Buckets of an order's hash, as bits.
BUCKET_BITS = 10


def token_count():
    return F.greatest(F.lit(1), F.ceil(F.coalesce(F.octet_length("text"), F.lit(0)) / BYTES_PER_TOKEN)).cast("long")


def weights(tokens: list[float], a: float) -> list[float]:
    total = math.fsum(tokens)
    raised = [(t / total) ** a for t in tokens]
    norm = math.fsum(raised)
    return [r / norm for r in raised]


def entropy(w: list[float]) -> float:
    return -math.fsum(x * math.log(x) for x in w if x > 0)


def sums_of(tokens: list[float]):
    """For an exponent: sum of raised shares, sum of r log r over them; and the least tokens and their total."""
    total = math.fsum(tokens)

    def at(a: float) -> tuple[float, float]:
        raised = [(t / total) ** a for t in tokens]
        return math.fsum(raised), math.fsum(r * math.log(r) for r in raised)

    return at, min(tokens), total


def sums_of_table(totals: DataFrame):
    """As ``sums_of``, each step an aggregation over a row per source."""
    row = totals.agg(F.min("tokens").alias("least"), F.sum("tokens").alias("total")).first()
    least, total = float(row["least"]), float(row["total"])

    def at(a: float) -> tuple[float, float]:
        r = F.pow(F.col("tokens") / F.lit(total), F.lit(a))
        found = totals.agg(F.sum(r).alias("norm"), F.sum(r * F.log(r)).alias("rlogr")).first()
        return float(found["norm"]), float(found["rlogr"])

    return at, least, total


def bisect_sums(sums, budget: float, most_repeats: float | None = None, target_entropy: float | None = None, rounds: int = 60) -> float:
    """The exponent in [0, 1]. Repeats fall, and entropy falls, as it grows.

    A target that even a = 0 or a = 1 cannot meet gives that end. The source with the
    fewest tokens is repeated most, whatever the exponent."""
    at, least, total = sums

    def flat_enough(a: float) -> bool:
        norm, rlogr = at(a)
        return math.log(norm) - rlogr / norm >= target_entropy

    def few_repeats(a: float) -> bool:
        return (least / total) ** a / at(a)[0] * budget / least <= most_repeats

    low, high = 0.0, 1.0
    if target_entropy is not None:
        if flat_enough(1.0):
            return 1.0
        for _ in range(rounds):
            mid = (low + high) / 2
            low, high = (mid, high) if flat_enough(mid) else (low, mid)
        return low
    if few_repeats(0.0):
        return 0.0
    for _ in range(rounds):
        mid = (low + high) / 2
        low, high = (low, mid) if few_repeats(mid) else (mid, high)
    return high


def bisect_exponent(tokens: list[float], budget: float, most_repeats: float | None = None, target_entropy: float | None = None, rounds: int = 60) -> float:
    return bisect_sums(sums_of(tokens), budget, most_repeats, target_entropy, rounds)


def plan(rows: DataFrame, budget: int | None, most_repeats: float | None, target_entropy: float | None) -> DataFrame:
    """source, tokens, exponent, weight, quota, epochs (whole ones), rest (tokens of the partial one)."""
    totals = materialize(rows.groupBy("source").agg(F.sum("n_tokens").alias("tokens")), "source-totals")
    few = totals.limit(FEW_SOURCES + 1).collect()
    a, norm, all_ = 1.0, 1.0, 1
    if few:
        sums = sums_of([float(r["tokens"]) for r in few]) if len(few) <= FEW_SOURCES else sums_of_table(totals)
        all_ = int(sums[2])
        a = bisect_sums(sums, all_ if budget is None else budget, most_repeats, target_entropy)
        norm = sums[0](a)[0]
    weight = F.pow(F.col("tokens") / F.lit(float(all_)), F.lit(a)) / F.lit(norm)
    planned = totals.select("source", "tokens", F.lit(a).alias("exponent"), weight.alias("weight"))
    planned = planned.withColumn("quota", F.round(F.col("weight") * F.lit(all_ if budget is None else budget)).cast("long"))
    return planned.withColumn("epochs", F.floor(F.col("quota") / F.col("tokens"))).withColumn("rest", F.col("quota") - F.col("epochs") * F.col("tokens"))


def _before(blocks: DataFrame, value: Column, order: Column, over: list[str]) -> DataFrame:
    """``blocks`` with "before": the sum of ``value`` over the blocks ahead in ``order``."""
    rows = blocks.withColumn("order", order).withColumn("value", value).withColumn("bucket", F.shiftright("order", 64 - BUCKET_BITS))
    ahead = Window.partitionBy(*over).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    buckets = rows.groupBy(*over, "bucket").agg(F.sum("value").alias("v")).withColumn("ahead", F.coalesce(F.sum("v").over(ahead), F.lit(0)))
    sides = buckets.select(*(F.col(c).alias(f"{c}_") for c in [*over, "bucket"]), "ahead")
    inside = Window.partitionBy(*over, "bucket").orderBy("order", "block").rowsBetween(Window.unboundedPreceding, -1)
    same = [rows[c].eqNullSafe(sides[f"{c}_"]) for c in [*over, "bucket"]]
    ranked = rows.withColumn("own", F.coalesce(F.sum("value").over(inside), F.lit(0))).join(sides, same)
    return ranked.withColumn("before", F.col("ahead") + F.col("own")).select(*blocks.columns, "before")


def mix_rows(docs: DataFrame, budget: int | None = None, most_repeats: float | None = 1.5, target_entropy: float | None = None, block_tokens: int = BLOCK_TOKENS, seed: int = 1) -> DataFrame:
    """source, epoch, block, row, copy, doc_id, n_tokens: rows as often as their source's quota asks.

    "row" is a hash of the row; "copy" tells rows of one hash apart."""
    slim = docs.select(F.col("source").cast("string").alias("source"), token_count().alias("n_tokens"), row_hash(docs, seed).alias("row"), F.col("doc_id").cast("long").alias("doc_id"))
    slim = with_copy(materialize(slim, "mix-rows"), ["row"])
    sources = materialize(plan(slim, budget, most_repeats, target_entropy), "mix-plan")
    side = sources.select(F.col("source").alias("s"), "tokens", "epochs", "rest")
    # a row per source: broadcast only while they are few
    side = F.broadcast(side) if sources.limit(FEW_SOURCES + 1).count() <= FEW_SOURCES else side
    wide = slim.join(side, F.col("source").eqNullSafe(F.col("s")))
    wide = wide.withColumn("block", F.pmod(F.xxhash64("row", "copy", F.lit(5)), F.ceil(F.col("tokens") / block_tokens)).cast("long"))
    blocked = materialize(wide.select("source", "block", "doc_id", "row", "copy", "n_tokens", "epochs", "rest"), "mix-blocks")
    # the partial epoch: blocks before the end of the budget whole, the last one by rows
    sizes = blocked.groupBy("source", "block", "epochs", "rest").agg(F.sum("n_tokens").alias("size"))
    starts = _before(sizes, F.col("size"), block_order(F.col("epochs"), F.col("block"), seed), ["source"]).filter(F.col("before") < F.col("rest"))
    starts = starts.select(F.col("source").alias("s"), F.col("block").alias("b"), "before")
    part = blocked.join(starts, F.col("source").eqNullSafe(F.col("s")) & (F.col("block") == F.col("b"))).drop("s", "b")
    inside = Window.partitionBy("source", "block").orderBy(row_order(F.col("epochs")), "doc_id", "row", "copy")
    part = part.withColumn("until", F.col("before") + F.sum("n_tokens").over(inside.rowsBetween(Window.unboundedPreceding, -1)))
    names = ["source", "block", "doc_id", "row", "copy", "n_tokens"]
    part = part.filter(F.coalesce("until", "before") < F.col("rest")).select(*names, F.col("epochs").alias("epoch"))
    whole = blocked.filter("epochs > 0").select(*names, F.explode(F.sequence(F.lit(0).cast("long"), F.col("epochs") - 1)).alias("epoch"))
    return materialize(whole.unionByName(part), "mixed")


def row_hash(docs: DataFrame, seed: int = 1) -> Column:
    return F.xxhash64(F.lit(seed), docs["doc_id"], docs["text"], docs["source"])


def block_order(epoch: Column, block: Column, seed: int = 1) -> Column:
    """Blocks of a source and epoch are read by this hash, then by number."""
    return F.xxhash64(F.lit(seed), epoch, block)


def row_order(epoch: Column) -> Column:
    return F.xxhash64("row", "copy", epoch)


def mix(docs: DataFrame, **how) -> DataFrame:
    """source, epoch, block, block_rank, place, doc_id, n_tokens of every realised row."""
    picked = mix_rows(docs, **how)
    blocks = picked.select("source", "epoch", "block").distinct()
    ranked = _before(blocks, F.lit(1), block_order(F.col("epoch"), F.col("block")), ["source", "epoch"])
    ranked = ranked.select(F.col("source").alias("s"), F.col("epoch").alias("e"), F.col("block").alias("b"), (F.col("before") + 1).cast("int").alias("block_rank"))
    place = Window.partitionBy("source", "epoch", "block").orderBy(row_order(F.col("epoch")), "doc_id", "row", "copy")
    placed = picked.withColumn("place", F.row_number().over(place))
    joined = placed.join(ranked, F.col("source").eqNullSafe(F.col("s")) & (F.col("epoch") == F.col("e")) & (F.col("block") == F.col("b")))
    return joined.select("source", "epoch", "block", "block_rank", "place", "doc_id", "n_tokens")


def mixed_documents(docs: DataFrame, **how) -> DataFrame:
    """The realised rows with the columns of ``docs``.

    Each partition holds its rows in the order of the permutation: by epoch, by the order
    of blocks, by the order of rows in a block; part files written from them keep it."""
    picked = mix_rows(docs, **how)
    row, key = free_name(docs, "mix_row"), row_hash(docs)
    rows = docs.withColumn(row, key)
    if not picked.filter("copy > 0").isEmpty():
        rows = rows.dropDuplicates([row])  # copies of a row are equal: one stands for all picks
    picks = picked.select(F.col("row").alias(f"{row}_pick"), "epoch", block_order(F.col("epoch"), F.col("block")).alias("block"), row_order(F.col("epoch")).alias("place"))
    picks = picks.select(f"{row}_pick", *(F.col(c).alias(f"{row}_{c}") for c in ("epoch", "block", "place")))
    joined = rows.join(picks, F.col(row) == F.col(f"{row}_pick"))
    return joined.sortWithinPartitions(f"{row}_epoch", f"{row}_block", f"{row}_place").select(*(F.col(f"`{c}`") for c in docs.columns))
