"""Near-duplicate documents by an LSH forest of min-hash signatures.

Texts with the same shingle set are one class from the start. Each class has one
signature; the forest's trees are sorted orders of the signature, each starting at
another of its values. In each order, neighbours that share a prefix of at least
``least_depth`` values are candidates; since neighbours in a sorted order are those
with the longest common prefix, the depth follows how crowded a region is. Candidates
are confirmed on whole shingle sets, in at most three rounds: each class's most alike
candidate, then the most alike candidate outside its component, then every candidate
pair that still joins two components. Pairs inside a component cannot change it.
Where more classes share the least prefix than are neighbours of each other and are not
yet one component, all of them meet: the range is dealt into blocks, every two blocks
meet in one group, and a group returns only the links that join components.

Defined cases: null, empty and blank texts have the empty set and are linked with
nothing; repeated rows and ties have one class, whose least doc_id stands for it; a
doc_id held by different texts is in the class of each; rows with null doc_id are linked
with nothing and stay alone; empty tables give no rows; further columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.llm.common import CHUNK_BYTES, components, discard, free_name, give_back, materialize, slices, tidy, utf8
from prunegraph.llm.shingles import minhash, shingle_sets

TREES = 16
HASHES = 64
LEAST_DEPTH = 3
NEIGHBOURS = 2
#: Estimated similarity under which a candidate is not confirmed: four standard errors.
SLACK = 0.2
#: Pairs up to which they are broadcast to the sets (checked by count).
SMALL_PAIRS = 50_000
ID_SLOTS = 1 << 20
#: Classes and bytes of sets in a block of a crowded prefix range.
BLOCK_CLASSES = 512
BLOCK_BYTES = 8 << 20
_PAIRS = 1 << 16


def signatures(docs: DataFrame, words: int, hashes: int = HASHES) -> DataFrame:
    """doc_id, hash of the text, n_shingles, set fingerprint and signature of every row."""

    def run(batches):
        for batch in batches:
            raw, offsets = utf8(batch.column(2))
            for a, b in slices(offsets, CHUNK_BYTES // 2):
                sets, at = shingle_sets(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], words)
                sig = minhash(sets, at, hashes)
                prints = np.zeros((b - a, 2), np.int64)
                for i in range(b - a):
                    if at[i + 1] > at[i]:
                        prints[i] = fingerprint(sets[at[i] : at[i + 1]])
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), pa.array(np.diff(at)), pa.array(prints[:, 0]), pa.array(prints[:, 1]), pa.array([x.tobytes() for x in sig], pa.binary())],
                    ["doc_id", "text_hash", "n_shingles", "print_a", "print_b", "sig"],
                )

    return docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("text_hash"), "text").mapInArrow(tidy(run), "doc_id long, text_hash long, n_shingles long, print_a long, print_b long, sig binary")


def _lcp(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Common prefix length, in 16-bit values, of rows of (n, 8) matrices."""
    return np.cumprod(a == b, axis=1).sum(axis=1)


def _forest_rows(classes: DataFrame, trees: int, hashes: int, carry: tuple[str, ...] = ()) -> DataFrame:
    """A row per class and tree: two longs that sort like eight signature values; ``carry`` are further longs."""
    step = hashes // trees
    names = ["tree", "k1", "k2", "id", *carry]

    def run(batches):
        for batch in batches:
            n = batch.num_rows
            sig = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint16).reshape(n, hashes)
            ids = [batch.column(0), *batch.columns[2:]]
            for t in range(trees):
                order = (np.arange(8) + t * step) % hashes
                key = np.ascontiguousarray(sig[:, order].astype(">u2")).view(">u8").astype(np.uint64)
                # sorts as a signed long
                key = (key ^ np.uint64(1 << 63)).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, t, np.int32)), pa.array(key[:, 0].copy()), pa.array(key[:, 1].copy()), *ids], names)

    return classes.select("id", "sig", *carry).mapInArrow(tidy(run), "tree int, " + ", ".join(f"{c} long" for c in names[1:]))


def candidates(classes: DataFrame, trees: int = TREES, hashes: int = HASHES, depth: int = LEAST_DEPTH, near: int = NEIGHBOURS) -> DataFrame:
    """Distinct pairs (a < b) that are neighbours in a sorted order."""
    spark = classes.sparkSession
    rows = materialize(_forest_rows(classes, trees, hashes), "forest")
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8)
    ordered = rows.repartitionByRange(parts, "tree", "k1", "k2", "id").sortWithinPartitions("tree", "k1", "k2", "id")

    def pairs_of(tree, k1, k2, ids):
        keys = np.stack([k1, k2], 1).view(np.uint64) ^ np.uint64(1 << 63)
        values = np.ascontiguousarray(keys.astype(">u8")).view(">u2").reshape(-1, 8)
        for d in range(1, near + 1):
            if len(ids) > d:
                same = (tree[d:] == tree[:-d]) & (_lcp(values[d:], values[:-d]) >= depth) & (ids[d:] != ids[:-d])
                x, y = ids[:-d][same], ids[d:][same]
                yield np.minimum(x, y), np.maximum(x, y)

    def run(batches):
        held, first = None, True
        names = ["a", "b", "tree", "k1", "k2", "id"]

        def out(a=(), b=(), edge=None):
            m, e = len(a), 0 if edge is None else len(edge[3])
            pad = lambda x, k, at: pa.array(np.concatenate([np.zeros(at, np.int64), np.asarray(x, np.int64), np.zeros(k - at - len(x), np.int64)]))
            n = m + e
            cols = [pad(a, n, 0), pad(b, n, 0)]
            edge = edge if e else [np.zeros(0, np.int64)] * 4
            cols.append(pa.array(np.concatenate([np.full(m, -1), edge[0]]).astype(np.int32)))
            cols += [pad(x, n, m) for x in edge[1:]]
            return pa.RecordBatch.from_arrays(cols, names)

        for batch in batches:
            if not batch.num_rows:
                continue
            new = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(4)]
            if first:
                yield out(edge=[x[:near] for x in new])
                first = False
            now = new if held is None else [np.concatenate([h, x]) for h, x in zip(held, new)]
            for a, b in pairs_of(*now):
                yield out(a, b)
            held = [x[-near:] for x in now]
        if held is not None:
            yield out(edge=held)

    found = materialize(ordered.mapInArrow(tidy(run), "a long, b long, tree int, k1 long, k2 long, id long"), "neighbours")
    # rows at the borders of the sorted partitions: 2 * near for each partition
    border = found.filter("tree >= 0").select("tree", "k1", "k2", "id").distinct()
    w = Window.partitionBy("tree").orderBy("k1", "k2", "id")
    across = None
    for d in range(1, near + 1):
        hop = border.select(F.col("id").alias("x"), F.lead("id", d).over(w).alias("y"), "k1", F.lead("k1", d).over(w).alias("n1"))
        hop = hop.filter("y is not null and x <> y").filter(F.shiftright("k1", 16 * max(0, 4 - depth)) == F.shiftright("n1", 16 * max(0, 4 - depth)))
        hop = hop.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
        across = hop if across is None else across.unionByName(hop)
    pairs = found.filter("tree < 0").select("a", "b").unionByName(across).distinct()
    out = materialize(pairs, "pairs")
    discard(rows, found)
    return out


def _estimate(pairs: DataFrame, classes: DataFrame, hashes: int) -> DataFrame:
    """Adds the share of equal signature values."""

    def run(batches):
        for batch in batches:
            n = batch.num_rows
            x, y = (np.frombuffer(b"".join(batch.column(i).to_pylist()), np.uint16).reshape(n, hashes) for i in (2, 3))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array((x == y).mean(axis=1))], ["a", "b", "like"])

    sig = classes.select("id", "sig")
    both = pairs.join(sig.withColumnsRenamed({"id": "a", "sig": "sig_a"}), "a").join(sig.withColumnsRenamed({"id": "b", "sig": "sig_b"}), "b")
    return both.select("a", "b", "sig_a", "sig_b").mapInArrow(tidy(run), "a long, b long, like double")


def fingerprint(shingles: np.ndarray) -> np.ndarray:
    """Two longs that name a set."""
    return np.frombuffer(hashlib.blake2b(shingles.tobytes(), digest_size=16).digest(), np.int64)


def class_sets(docs: DataFrame, heads: DataFrame, ids: DataFrame, words: int) -> DataFrame:
    """(id, set) for the listed classes, from a text of their representative that has the set."""

    def run(batches):
        last = None
        for batch in batches:
            raw, offsets = utf8(batch.column(1))
            prints = np.stack([batch.column(i).to_numpy(zero_copy_only=False) for i in (2, 3)], 1)
            names = batch.column(0).to_numpy(zero_copy_only=False)
            for a, b in slices(offsets, CHUNK_BYTES // 2):
                sets, at = shingle_sets(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], words)
                found, data = [], []
                for i in range(b - a):
                    own = sets[at[i] : at[i + 1]]
                    if names[a + i] != last and (fingerprint(own) == prints[a + i]).all():
                        last = names[a + i]
                        found.append(last)
                        data.append(own.tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(found, pa.int64()), pa.array(data, pa.binary())], ["id", "set"])

    wanted = ids.join(heads.select("id", "rep", "print_a", "print_b"), "id")
    # a fixed number of hash slots of the wanted documents keeps most other texts out of the shuffle
    slot = F.pmod(F.xxhash64("rep"), F.lit(ID_SLOTS)).cast("int")
    slots = wanted.select(slot.alias("slot")).distinct()
    text = docs.select(F.col("doc_id").cast("long").alias("rep"), "text").withColumn("slot", slot).join(F.broadcast(slots), "slot", "left_semi").drop("slot")
    # rows of a class follow each other, so that one of them is taken
    rows = text.join(wanted, "rep").select("id", "text", "print_a", "print_b").sortWithinPartitions("id")
    return rows.mapInArrow(tidy(run), "id long, set binary")


def confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs whose sets have 100 * intersection >= percent * union."""

    def run(batches):
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            x, y = batch.column(2), batch.column(3)
            for i in range(batch.num_rows):
                p, q = (np.frombuffer(c[i].as_buffer(), np.uint64) for c in (x, y))
                if min(len(p), len(q)) * 100 >= percent * max(len(p), len(q)):
                    both = len(np.intersect1d(p, q, assume_unique=True))
                    keep[i] = 100 * both >= percent * (len(p) + len(q) - both)
            mask = pa.array(keep)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(mask), batch.column(1).filter(mask)], ["a", "b"])

    small = pairs.count() <= SMALL_PAIRS
    side = (lambda df: F.broadcast(df)) if small else (lambda df: df)
    one = sets.withColumnsRenamed({"id": "a", "set": "set_a"}).join(side(pairs), "a")
    other = sets.withColumnsRenamed({"id": "b", "set": "set_b"}).join(side(pairs.select("b", "a")), "b")
    return one.join(other, ["a", "b"]).select("a", "b", "set_a", "set_b").mapInArrow(tidy(run), "a long, b long")


def _bits(sets: list[np.ndarray]) -> np.ndarray:
    """A row of bits per set, over the shingles that occur in more than one."""
    shingle, n = np.unique(np.concatenate(sets), return_counts=True)
    shingle = shingle[n > 1]
    out = np.zeros((len(sets), -(-max(1, len(shingle)) // 64)), np.uint64)
    for i, s in enumerate(sets):
        row = np.zeros(out.shape[1] * 64, bool)
        at = np.searchsorted(shingle, s)
        inside = at < len(shingle)
        at, s = at[inside], s[inside]
        row[at[shingle[at] == s]] = True
        out[i] = np.packbits(row).view(np.uint64)
    return out


def _joining(ids: np.ndarray, component: np.ndarray, first: np.ndarray, sig: np.ndarray, sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Confirmed pairs that join the components of a group; ``first`` and other rows meet if both occur."""
    parent = {int(c): int(c) for c in component}

    def find(c):
        while parent[c] != c:
            parent[c] = parent[parent[c]]
            c = parent[c]
        return c

    one = other = np.arange(len(ids))
    if not first.all():
        one, other = np.flatnonzero(first), np.flatnonzero(~first)
    like = np.zeros((len(one), len(other)), np.uint8)
    for k in range(sig.shape[1]):
        like += sig[one, k][:, None] == sig[other, k][None]
    good = (like >= (percent / 100 - SLACK) * sig.shape[1]) & (component[one][:, None] != component[other][None])
    if first.all():
        good &= one[:, None] < other[None]
    x, y = np.nonzero(good)
    order = np.argsort(-like[x, y].astype(np.int16), kind="stable")
    x, y = one[x[order]], other[y[order]]
    if not len(x):
        return []
    bits, size = _bits(sets), np.array([len(s) for s in sets])
    step = max(1, min(_PAIRS, (32 << 20) // (8 * bits.shape[1])))
    found, now = [], component
    while len(x):
        a, b, x, y = x[:step], y[:step], x[step:], y[step:]
        both = np.bitwise_count(bits[a] & bits[b]).sum(axis=1, dtype=np.int64)
        linked = 100 * both >= percent * (size[a] + size[b] - both)
        before = len(found)
        for i, j in zip(a[linked].tolist(), b[linked].tolist()):
            p, q = find(int(component[i])), find(int(component[j]))
            if p != q:
                parent[max(p, q)] = min(p, q)
                found.append((int(min(ids[i], ids[j])), int(max(ids[i], ids[j]))))
        if len(found) > before:
            now = np.array([find(int(c)) for c in component])
        rest = now[x] != now[y]
        x, y = x[rest], y[rest]
    return found


def crowded_links(docs: DataFrame, heads: DataFrame, label: DataFrame | None, words: int, percent: int, trees: int, hashes: int, depth: int = LEAST_DEPTH, near: int = NEIGHBOURS) -> DataFrame | None:
    """Components after all classes of every crowded prefix range have met."""
    place = ["tree", "prefix"]

    def labelled(df):
        if label is None:
            return df.withColumn("component", F.col("id"))
        return df.join(label, "id", "left").withColumn("component", F.coalesce("component", "id"))

    def open_ranges(rows):
        ranges = rows.groupBy(place).agg(
            F.count(F.lit(1)).alias("n"), F.sum("n_shingles").alias("shingles"), F.min("component").alias("least"), F.max("component").alias("most")
        )
        blocks = F.greatest(F.ceil(F.col("n") / BLOCK_CLASSES), F.ceil(F.col("shingles") * 8 / BLOCK_BYTES)).cast("int")
        # up to near + 1 classes are all neighbours
        return materialize(ranges.filter((F.col("n") > near + 1) & (F.col("least") != F.col("most"))).select(*place, blocks.alias("blocks")), "ranges")

    def within(rows, ranges):
        return rows.join(F.broadcast(ranges) if ranges.count() <= SMALL_PAIRS else ranges, place)

    def run(key, group):
        first = group["block"].to_numpy() == key[2].as_py()
        ids, component = (group[c].to_numpy() for c in ("id", "component"))
        sig = np.frombuffer(b"".join(group["sig"].to_pylist()), np.uint16).reshape(len(ids), hashes)
        sets = [np.frombuffer(s, np.uint64) for s in group["set"].to_pylist()]
        pairs = _joining(ids, component, first, sig, sets, percent) if first.any() else []
        if group.nbytes > BLOCK_BYTES // 8:
            give_back()
        return pa.table({"a": pa.array([p[0] for p in pairs], pa.int64()), "b": pa.array([p[1] for p in pairs], pa.int64())})

    known = materialize(labelled(heads.select("id", "sig", "n_shingles")), "labelled")
    rows = _forest_rows(known, trees, hashes, ("component", "n_shingles")).withColumn("prefix", F.shiftright("k1", 16 * max(0, 4 - depth)))
    ranges = open_ranges(rows)
    if ranges.isEmpty():
        discard(known, ranges)
        return label
    members = materialize(within(rows, ranges).select(*place, "id", "n_shingles"), "members")
    ids = members.select("id").distinct()
    sets = materialize(class_sets(docs, heads, ids, words).join(heads.select("id", "sig"), "id"), "member-sets")
    discard(known, ranges)
    # a range that became one component in an earlier tree needs no second look
    for start, end in ((0, 1), (1, 4), (4, trees)):
        now = labelled(members.filter(F.col("tree").between(start, end - 1)))
        ranges = open_ranges(now)
        if ranges.isEmpty():
            continue
        placed = within(now, ranges).withColumn("block", F.pmod(F.xxhash64("id", F.lit(5)), F.col("blocks")).cast("int"))
        met = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        met = met.select(*place, F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "id", "component").join(sets, "id")
        more = materialize(met.groupBy(*place, "lo", "hi").applyInArrow(run, "a long, b long"), "crowded")
        if not more.isEmpty():
            label = components(more, "near", label)
        discard(ranges, more)
    return label


def near_classes(docs: DataFrame, words: int = 5, percent: int = 80, trees: int = TREES, hashes: int = HASHES) -> DataFrame:
    """doc_id, text_hash, n_shingles, component_id, group of every row of ``docs``.

    "group" names the component; it is null for rows that take no part."""
    rows = materialize(signatures(docs, words, hashes), "signatures")
    full = rows.filter("n_shingles > 0 and doc_id is not null")
    heads = full.groupBy("print_a", "print_b").agg(F.min("doc_id").alias("rep"), F.first("sig").alias("sig"), F.min("n_shingles").alias("n_shingles"))
    heads = materialize(heads.withColumn("id", F.xxhash64("print_a", "print_b")), "classes")
    pairs = candidates(heads, trees, hashes)
    left = materialize(_estimate(pairs, heads, hashes).filter(F.col("like") >= percent / 100 - SLACK), "likely")
    discard(pairs)
    ids = left.select(F.col("a").alias("id")).union(left.select("b")).distinct()
    sets = materialize(class_sets(docs, heads, ids, words), "sets")
    label, tried = None, None
    for turn in range(3):
        open_ = left
        if label is not None:
            open_ = (
                left.join(tried, ["a", "b"], "left_anti")
                .join(label.withColumnsRenamed({"id": "a", "component": "ca"}), "a", "left")
                .join(label.withColumnsRenamed({"id": "b", "component": "cb"}), "b", "left")
                .filter(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b", "like")
            )
        if turn < 2:
            ends = open_.select(F.col("a").alias("e"), "a", "b", "like").unionByName(open_.select(F.col("b").alias("e"), "a", "b", "like"))
            best = ends.groupBy("e").agg(F.max(F.struct("like", -F.col("a"), -F.col("b"), "a", "b")).alias("m"))
            open_ = best.select("m.a", "m.b").distinct()
        chosen = materialize(open_.select("a", "b"), "chosen")
        if chosen.isEmpty():
            break
        good = materialize(confirm(chosen, sets, percent), "good")
        tried = chosen if tried is None else tried.unionByName(chosen)
        label = components(good, "near", label)
        discard(good)
    label = crowded_links(docs, heads, label, words, percent, trees, hashes)
    group = F.col("id") if label is None else F.coalesce("component", "id")
    named = (heads if label is None else heads.join(label, "id", "left")).select("print_a", "print_b", "rep", group.alias("group"))
    least = named.groupBy("group").agg(F.min("rep").alias("least"))
    merged = named.join(least, "group").select("print_a", "print_b", "group", "least")
    linked = rows.join(merged, ["print_a", "print_b"], "left")
    part = (F.col("n_shingles") > 0) & F.col("doc_id").isNotNull()
    return linked.select("doc_id", "text_hash", "n_shingles", F.when(part, F.col("least")).otherwise(F.col("doc_id")).alias("component_id"), F.when(part, F.col("group")).alias("group"))


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row of ``docs``."""
    found = near_classes(docs, words, percent).select("doc_id", "n_shingles", "component_id")
    return found.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def without_near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """One row of each group, and all rows that take no part, with the columns of ``docs``.

    The row with the least doc_id stays; where texts share it, the one with the least hash."""
    found = materialize(near_classes(docs, words, percent).filter("group is not null").select("doc_id", "text_hash", "group"), "near-groups")
    best = found.groupBy("group").agg(F.min(F.struct("doc_id", "text_hash")).alias("best")).select("best.*")
    rows = found.groupBy("doc_id", "text_hash").agg(F.count(F.lit(1)).alias("copies"))
    doc, text = free_name(docs, "near_doc"), free_name(docs, "near_text")
    gone = rows.join(best, ["doc_id", "text_hash"], "left_anti").select(F.col("doc_id").alias(doc), F.col("text_hash").alias(text))
    left = docs.join(gone, (docs["doc_id"].cast("long") == F.col(doc)) & (F.xxhash64(docs["text"]) == F.col(text)), "left_anti")
    if rows.join(best, ["doc_id", "text_hash"], "left_semi").filter("copies > 1").isEmpty():
        return left
    # a repeated row is a copy as well; rows without an id or words are none
    key = free_name(docs, "near_key")
    blank = F.col("doc_id").isNull() | ~F.coalesce(F.col("text"), F.lit("")).rlike("[^\\x20\\x09-\\x0D]")
    keyed = left.withColumn(key, F.when(~blank, F.xxhash64("doc_id", "text")))
    return keyed.filter(F.col(key).isNull()).unionByName(keyed.filter(F.col(key).isNotNull()).dropDuplicates([key])).drop(key)
