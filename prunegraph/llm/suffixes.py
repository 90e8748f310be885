"""Exact removal of repeated passages with sharded suffix arrays.

A byte goes if a ``length``-byte string over it also starts earlier (smaller doc_id, or
the same document and an earlier start), judged on the input as it is.

1. Where repeats can be. Every window of ``length`` bytes picks an anchor, its least
   hashed ``gram``-byte string, leftmost on ties. Equal windows pick equal anchors, so a
   window whose anchor occurs once in the corpus repeats nothing. Successive windows
   with one anchor form a stretch. Equal stretches are collapsed to their first
   occurrence before anything is sent, inside a task and then across tasks; an anchor
   with many different stretches inside one task is not gathered at all.
2. Different stretches of one anchor (the ends of shared passages) go, as bytes, to
   shards of ``SHARD_BYTES``: ranges of (anchor, content), so that an anchor of any
   weight is spread. Each shard builds a suffix array by Larsson-Sadakane refinement and
   common prefixes by Kasai's rule; suffixes that share ``length`` bytes are one window
   and all but the earliest go.
3. An anchor that the border of a shard cuts has equal windows in several shards. Each
   shard packs the windows that such anchors keep into one sorted array; arrays are
   merged two at a time by binary search of one in the other, a range of values per task.
4. Removed windows meet their documents again and become byte runs.

Defined cases: null text is empty; texts shorter than ``length`` stay; equal rows count
as one document (runs apply to each of them); different texts under one doc_id are
documents of their own, in the order of a hash of their text; a row without doc_id takes
no part and stays whole; empty tables give no rows; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prunegraph.llm.common import free_name, long_view, materialize, mix, slices, tidy, utf8, utf8_of
from prunegraph.llm.shingles import powers, sums

LENGTH = 100
GRAM = 20
#: Bytes of text whose anchors are settled together inside a task.
TASK_BYTES = 16 << 20
#: Bytes of one suffix array.
SHARD_BYTES = 2 << 20
#: Different stretches of one anchor that a task still sends to be settled with others.
GATHERED = 8
#: Windows of cut anchors that one task merges, and that a task packs at once.
MERGED = 1 << 18
_POSITION_BITS = 20
#: Bits of a position inside a text; what tells texts of one doc_id apart lies above.
_TEXT_BITS = 32


def _load8(raw: np.ndarray, at: int, n: int) -> np.ndarray:
    """The little-endian 8-byte words that start at ``at``, ``at`` + 1, ..."""
    return np.ndarray((n,), "<u8", raw, at, (1,))


def gram_hashes(raw: np.ndarray, gram: int) -> np.ndarray:
    """Hash of every ``gram``-byte string; ``gram`` is at least 8."""
    n = len(raw) - gram + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    raw = np.ascontiguousarray(raw)
    h = _load8(raw, 0, n) * np.uint64(0x9E3779B97F4A7C15)
    for at in [*range(8, gram - 8, 8), gram - 8]:
        h = (h ^ (h >> np.uint64(32)) ^ _load8(raw, at, n)) * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


def window_minimum(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of x[i : i + w] for every whole window."""
    n = len(x) - w + 1
    if n <= 0:
        return x[:0]
    blocks = -(-len(x) // w)
    padded = np.full(blocks * w, np.iinfo(np.uint64).max, np.uint64)
    padded[: len(x)] = x
    grid = padded.reshape(blocks, w)
    ahead = np.minimum.accumulate(grid, axis=1).ravel()
    behind = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[w - 1 : w - 1 + n])


def stretches(raw: np.ndarray, offsets: np.ndarray, length: int, gram: int):
    """(row, start in the row, windows, anchor hash, content hash) of each stretch."""
    h = gram_hashes(raw, gram)
    n = len(raw) - length + 1
    if n <= 0:
        z = np.zeros(0, np.int64)
        return z, z, z, z, z
    low = np.uint64((1 << _POSITION_BITS) - 1)
    least = window_minimum((h & ~low) | np.arange(len(h), dtype=np.uint64), length - gram + 1)[:n]
    anchor = (least & low).astype(np.int64)
    inside = np.ones(n + 1, bool)  # windows that stay inside a row
    for edge in offsets[1:-1]:
        inside[max(0, edge - length + 1) : edge] = False
    inside[n] = False
    start = inside[:n].copy()
    start[1:] &= (anchor[1:] != anchor[:-1]) | ~inside[: n - 1]
    first = np.flatnonzero(start)
    stop = inside[:n].copy()
    stop[:-1] &= (anchor[1:] != anchor[:-1]) | ~inside[1:n]
    last = np.flatnonzero(stop)
    windows = last - first + 1
    total = sums(raw)
    _, down = powers(len(raw) + 1)
    content = mix((total[last + length] - total[first]) * down[first])
    row = np.searchsorted(offsets, first, "right") - 1
    return row, first - offsets[row], windows, long_view(h[anchor[first]]), long_view((content << np.uint64(7)) | windows.astype(np.uint64))


def _row_stretches(raw, offsets, length, gram):
    """As ``stretches``, for rows of any size; starts of long rows are shifted back."""
    most = 1 << _POSITION_BITS
    for a, b in slices(offsets, most):
        lo, hi = int(offsets[a]), int(offsets[b])
        if hi - lo <= most:
            yield a, 0, stretches(raw[lo:hi], offsets[a : b + 1] - lo, length, gram)
        else:
            for s in range(lo, hi, most - length + 1):
                e = min(s + most, hi)
                yield a, s - lo, stretches(raw[s:e], np.array([0, e - s]), length, gram)


_KINDS = "anchor long, content long, doc long, start long, kind int"
_NAMES = ["anchor", "content", "doc", "start", "kind"]
STRETCH, GONE, OPEN, MARK = 0, 1, 2, 3
#: Stands in the place of a content; says that its anchor has several.
_SEVERAL = np.int64(np.iinfo(np.int64).min)


def identity(docs: DataFrame) -> tuple[Column, bool]:
    """What tells the texts of one doc_id apart, and whether any doc_id is repeated.

    The first is 0 where no doc_id has several texts, else a hash of the text."""
    text = F.xxhash64("text")
    ids = docs.select(F.col("doc_id").cast("long").alias("doc"), text.alias("h")).filter("doc is not null")
    seen = ids.groupBy("doc").agg((F.min("h") != F.max("h")).alias("several"), (F.count(F.lit(1)) > 1).alias("again"))
    flags = seen.agg(F.max("several").alias("several"), F.max("again").alias("again")).first()
    return (text.bitwiseAND((1 << 31) - 1) if flags["several"] else F.lit(0).cast("long")), bool(flags["again"])


def _batch(anchor, content, doc, start, kind: int):
    n = len(doc)
    return pa.RecordBatch.from_arrays([pa.array(anchor), pa.array(content), pa.array(doc), pa.array(start), pa.array(np.full(n, kind, np.int32))], _NAMES)


def _task_stretches(rows: DataFrame, length: int, gram: int) -> DataFrame:
    """Stretches that are first of their content in the task, and the ones that are not.

    Stretches of an anchor with more than ``GATHERED`` contents in the task are OPEN at
    once; a MARK tells the others of that anchor."""

    def settle(parts):
        anchor, content, doc, start = (np.concatenate(x) for x in zip(*parts))
        order = np.lexsort((start, doc, content, anchor))
        anchor, content, doc, start = anchor[order], content[order], doc[order], start[order]
        new = np.ones(len(doc), bool)
        new[1:] = (anchor[1:] != anchor[:-1]) | (content[1:] != content[:-1])
        head = np.maximum.accumulate(np.where(new, np.arange(len(doc)), 0))
        later = ~new & ((doc != doc[head]) | (start != start[head]))
        if later.any():
            yield _batch(anchor[later], content[later], doc[later], start[later], GONE)
        anchor, content, doc, start = anchor[new], content[new], doc[new], start[new]
        first = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]])) if len(anchor) else np.zeros(0, np.int64)
        count = np.diff(np.append(first, len(anchor)))
        crowded = np.repeat(count > GATHERED, count)
        if crowded.any():
            yield _batch(anchor[crowded], content[crowded], doc[crowded], start[crowded], OPEN)
            marked = anchor[first[count > GATHERED]]
            none = np.zeros(len(marked), np.int64)
            yield _batch(marked, np.full(len(marked), _SEVERAL), none, none, MARK)
        yield _batch(anchor[~crowded], content[~crowded], doc[~crowded], start[~crowded], STRETCH)

    def run(batches):
        held, size = [], 0
        for batch in batches:
            raw, offsets = utf8(batch.column(2))
            ids, nth = (batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in (0, 1))
            for a, shift, (row, start, _, anchor, content) in _row_stretches(raw, offsets, length, gram):
                held.append((anchor, content, ids[a + row], (nth[a + row] << _TEXT_BITS) + start + shift))
            size += len(raw)
            if size >= TASK_BYTES:
                yield from settle(held)
                held, size = [], 0
        if held:
            yield from settle(held)

    return rows.filter(f"octet_length(text) >= {length}").mapInArrow(tidy(run), _KINDS)


def _settle_anchors(rows: DataFrame) -> DataFrame:
    """Across tasks: later occurrences of a content go; anchors with several contents stay open."""

    def run(batches):
        first = None  # (anchor, content, doc, start) of the last content seen
        waiting = False  # it is open as soon as another content of its anchor comes
        for batch in batches:
            if not batch.num_rows:
                continue
            anchor, content, doc, start, kind = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(5))
            for known in (GONE, OPEN):
                at = kind == known
                if at.any():
                    yield _batch(anchor[at], content[at], doc[at], start[at], known)
            rest = (kind == STRETCH) | (kind == MARK)
            anchor, content, doc, start = (x[rest] for x in (anchor, content, doc, start))
            if not len(doc):
                continue
            held = 0
            if first is not None:
                anchor, content, doc, start = (np.concatenate([[f], x]) for f, x in zip(first, (anchor, content, doc, start)))
                held = 1
            new = np.ones(len(doc), bool)
            new[1:] = (anchor[1:] != anchor[:-1]) | (content[1:] != content[:-1])
            head = np.maximum.accumulate(np.where(new, np.arange(len(doc)), 0))
            later = ~new & ((doc != doc[head]) | (start != start[head]))
            if later.any():
                yield _batch(anchor[later], content[later], doc[later], start[later], GONE)
            heads = np.flatnonzero(new)
            same = anchor[heads][1:] == anchor[heads][:-1]
            is_open = np.zeros(len(heads), bool)
            is_open[1:] |= same
            is_open[:-1] |= same
            send = is_open.copy()
            if held and not waiting:
                send[0] = False  # sent before
            waiting = not is_open[-1] if len(heads) > 1 else (waiting if held else True)
            send = heads[send]
            send = send[content[send] != _SEVERAL]
            if len(send):
                yield _batch(anchor[send], content[send], doc[send], start[send], OPEN)
            k = heads[-1]
            first = (anchor[k], content[k], doc[k], start[k])

    # what is settled already only passes through, dealt evenly
    key = F.when(F.col("kind").isin(GONE, OPEN), F.xxhash64("doc", "start")).otherwise(F.col("anchor"))
    return rows.repartition(key).sortWithinPartitions("anchor", "content", "doc", "start").mapInArrow(tidy(run), _KINDS)


def suffix_array(raw: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes of ``raw`` in the order of their first ``depth`` bytes at least.

    Larsson-Sadakane refinement: groups of suffixes that agree on h bytes are sorted
    by the group of what follows h bytes later; only groups that still hold several
    suffixes are looked at again, and h doubles."""
    n = len(raw)
    padded = np.zeros(n + 8, np.uint8)
    padded[:n] = raw
    key = np.ndarray((n,), ">u8", padded, 0, (1,)).astype(np.uint64)
    sa = np.argsort(key)
    ordered = key[sa]
    new = np.ones(n, bool)
    new[1:] = ordered[1:] != ordered[:-1]
    group = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    rank = np.empty(n + 1, np.int64)
    rank[n] = -1
    rank[sa] = group
    h = 8
    while h < depth:
        single = new.copy()
        single[:-1] &= new[1:]
        at = np.flatnonzero(~single)
        if not len(at):
            break
        some = sa[at]
        pair = rank[some] * (n + 2) + rank[np.minimum(some + h, n)] + 1
        order = np.argsort(pair)
        some, pair = some[order], pair[order]
        sa[at] = some
        split = np.ones(len(at), bool)
        split[1:] = pair[1:] != pair[:-1]
        new[at] = split
        rank[some] = np.maximum.accumulate(np.where(split, at, 0))
        h *= 2
    return sa


def common_prefixes(raw: np.ndarray, sa: np.ndarray, base: np.ndarray, windows: np.ndarray, most: int) -> np.ndarray:
    """Common prefix, up to ``most`` bytes, of each suffix in ``sa`` with the one before.

    ``sa`` holds the suffixes at base[k] .. base[k] + windows[k] - 1. Kasai's rule: going
    one byte on in the text loses one byte of common prefix at most, if the suffix before
    goes on as well and still sorts before (suffixes equal to the sorted depth may not).
    All strings advance together."""
    place = np.full(len(raw), -1, np.int64)
    place[sa] = np.arange(len(sa))
    lcp = np.zeros(len(sa), np.int64)
    size = np.zeros(len(base), np.int64)
    before_last = np.full(len(base), -1, np.int64)
    for step in range(int(windows.max(initial=0))):
        lane = np.flatnonzero(windows > step)
        here = base[lane] + step
        at = place[here]
        before = np.where(at > 0, sa[np.maximum(at - 1, 0)], -1)
        beside = place[np.minimum(before_last[lane] + 1, len(raw) - 1)]
        follows = (before_last[lane] >= 0) & (beside >= 0) & (beside < at)
        l = np.where(follows & (before >= 0), np.maximum(size[lane] - 1, 0), 0)
        active = np.flatnonzero(before >= 0)
        while len(active):
            p, q = here[active] + l[active], before[active] + l[active]
            ok = (l[active] < most) & (np.maximum(p, q) < len(raw))
            ok[ok] = raw[p[ok]] == raw[q[ok]]
            active = active[ok]
            l[active] += 1
        lcp[at] = l
        size[lane], before_last[lane] = l, before
    return lcp


def shard_repeats(raw: np.ndarray, base: np.ndarray, windows: np.ndarray, doc: np.ndarray, start: np.ndarray, length: int):
    """(string, window) of every window that is not the earliest of its content, and of the earliest."""
    sa = suffix_array(raw, length)
    string = np.searchsorted(base, sa, "right") - 1
    whole = sa - base[string] < windows[string]
    sa, string = sa[whole], string[whole]
    lcp = common_prefixes(raw, sa, base, windows, length)
    new = np.ones(len(sa), bool)
    new[1:] = lcp[1:] < length
    klass = np.cumsum(new) - 1
    begins = start[string] + sa - base[string]
    order = np.lexsort((begins, doc[string], klass))
    first = np.ones(len(sa), bool)
    first[1:] = klass[order][1:] != klass[order][:-1]
    head = order[np.maximum.accumulate(np.where(first, np.arange(len(sa)), 0))]
    later = (doc[string[order]] != doc[string[head]]) | (begins[order] != begins[head])
    gone, kept = order[later], order[first]
    return (string[gone], sa[gone] - base[string[gone]]), (string[kept], sa[kept] - base[string[kept]])


def _window_runs(doc: np.ndarray, begin: np.ndarray):
    """Successive window starts of a document as (doc, first start, windows)."""
    order = np.lexsort((begin, doc))
    doc, begin = doc[order], begin[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (begin[1:] > begin[:-1] + 1)
    at = np.flatnonzero(new)
    last = np.append(at, len(doc))[1:] - 1
    return doc[at], begin[at], begin[last] - begin[at] + 1


def _dealt(open_: DataFrame, length: int) -> DataFrame:
    """Open stretches with the shard they go to and whether a border may cut their anchor.

    Tasks hold ranges of (anchor, content, doc); shards are the next ``SHARD_BYTES`` of a
    task. Rows of the last anchor wait until it ends or is known to be cut, so less than a
    shard is held."""
    names = ["anchor", "doc", "start", "windows", "shard", "cut"]

    def run(batches):
        from pyspark import TaskContext

        task = TaskContext.get().partitionId() << 32
        done, held, known = 0, None, None

        def rows(columns, cut):
            return pa.RecordBatch.from_arrays([*(pa.array(c) for c in columns), pa.array(cut)], names)

        for batch in batches:
            if not batch.num_rows:
                continue
            anchor, doc, start, windows = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(4))
            ends = done + np.cumsum(windows + length - 1)
            columns = [anchor, doc, start, windows, task + (ends - windows - length + 1) // SHARD_BYTES]
            done = int(ends[-1])
            known = anchor[0] if known is None and held is None else known  # may go on from the task before
            if held is not None:
                columns = [np.concatenate(pair) for pair in zip(held, columns)]
            anchor, shard = columns[0], columns[4]
            first = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]]))
            last = np.append(first[1:], len(anchor)) - 1
            cut = (shard[first] != shard[last]) | (anchor[first] == known if known is not None else False)
            if cut[-1]:
                known, held, until = anchor[-1], None, len(anchor)
            else:
                until = int(first[-1])
                held = [c[until:] for c in columns]
            if until:
                yield rows([c[:until] for c in columns], np.repeat(cut, last - first + 1)[:until])
        if held is not None:
            yield rows(held, np.ones(len(held[0]), bool))

    order = ["anchor", "content", "doc"]
    ranged = open_.repartitionByRange(*order).sortWithinPartitions(*order).select("anchor", "doc", "start", "windows")
    return ranged.mapInArrow(tidy(run), "anchor long, doc long, start long, windows long, shard long, cut boolean")


def _bytes_of(dealt: DataFrame, rows: DataFrame, length: int) -> DataFrame:
    """Fetch the bytes of open stretches from their documents."""
    nth = F.shiftright("start", _TEXT_BITS)
    wanted = dealt.groupBy("doc", nth.alias("nth")).agg(F.collect_list(F.struct("anchor", "start", "windows", "shard", "cut")).alias("parts"))

    def run(batches):
        for batch in batches:
            raw, offsets = utf8(batch.column(1))
            for a, b in slices(offsets):
                lists = batch.column(2).slice(a, b - a)
                row = a + np.repeat(np.arange(b - a), pa.compute.list_value_length(lists).to_numpy(zero_copy_only=False))
                parts = lists.flatten()
                anchor, start, windows, shard, cut = (parts.field(i) for i in range(5))
                at = start.to_numpy(zero_copy_only=False) & ((1 << _TEXT_BITS) - 1)
                size = windows.to_numpy(zero_copy_only=False) + length - 1
                ends = np.cumsum(size)
                take = np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(offsets[row] + at - (ends - size), size)
                cuts = np.concatenate([[0], ends]).astype(np.int32)
                data = pa.Array.from_buffers(pa.binary(), len(at), [None, pa.py_buffer(cuts), pa.py_buffer(raw[take])])
                doc = batch.column(0).take(pa.array(row))
                yield pa.RecordBatch.from_arrays([anchor, shard, cut, doc, start, windows, data], ["anchor", "shard", "cut", "doc", "start", "windows", "data"])

    return rows.join(wanted, ["doc", "nth"]).select("doc", "text", "parts").mapInArrow(tidy(run), "anchor long, shard long, cut boolean, doc long, start long, windows long, data binary")


# A pack is a matrix of four rows, sorted by the first: the value of a window's bytes, its
# anchor, and where its earliest occurrence starts (doc, start).


def merge_packs(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both packs as one by binary search, and the (doc, start) of windows that also start earlier."""
    if not a.shape[1] or not b.shape[1]:
        return (a if a.shape[1] else b), a[2:, :0]
    at = np.searchsorted(a[0], b[0])
    near = np.minimum(at, a.shape[1] - 1)
    same = (a[0, near] == b[0]) & (a[1, near] == b[1])
    sooner = same & ((b[2] < a[2, near]) | ((b[2] == a[2, near]) & (b[3] < a[3, near])))
    later = same & ((b[2] > a[2, near]) | ((b[2] == a[2, near]) & (b[3] > a[3, near])))
    late = np.concatenate([a[2:, near[sooner]], b[2:, later]], 1)
    a = a.copy()
    a[:, near[sooner]] = b[:, sooner]
    return np.insert(a, at[~same], b[:, ~same], axis=1), late


def merge_all(packs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """All packs as one, the two smallest first."""
    heap = [(p.shape[1], i, p) for i, p in enumerate(packs)]
    heapq.heapify(heap)
    late, n = [np.zeros((2, 0), np.int64)], len(heap)
    while len(heap) > 1:
        (_, _, a), (_, _, b) = heapq.heappop(heap), heapq.heappop(heap)
        both, more = merge_packs(a, b)
        late.append(more)
        heapq.heappush(heap, (both.shape[1], n, both))
        n += 1
    return (heap[0][2] if heap else np.zeros((4, 0), np.int64)), np.concatenate(late, 1)


_FOUND = "kind int, doc long, start long, windows long, range int, pack binary"


def _found(doc, start, windows):
    n = len(doc)
    return pa.RecordBatch.from_arrays([pa.array(np.full(n, GONE, np.int32)), pa.array(doc), pa.array(start), pa.array(windows), pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary())], ["kind", "doc", "start", "windows", "range", "pack"])


def _shards(strings: DataFrame, length: int, ranges: int) -> DataFrame:
    """Suffix arrays over whole shards, several small ones at once.

    Rows: kind GONE (doc, start, windows), or OPEN, a pack of the windows kept of cut
    anchors whose values lie in one of ``ranges`` ranges."""

    def settle(parts):
        table = pa.Table.from_batches(parts).combine_chunks()
        anchor, _, cut, doc, start, windows = (table.column(i).to_numpy() for i in range(6))
        raw, offsets = utf8_of(table.column(6))
        (gs, gw), (ks, kw) = shard_repeats(raw, offsets[:-1], windows, doc, start, length)
        gone = _window_runs(doc[gs], start[gs] + gw)
        keep = cut[ks]
        ks, kw = ks[keep], kw[keep]
        total = sums(raw)
        _, down = powers(len(raw) + 1)
        at = offsets[ks] + kw
        value = long_view(mix((total[at + length] - total[at]) * down[at]))
        pack = np.stack([value, anchor[ks], doc[ks], start[ks] + kw])
        return gone, pack[:, np.argsort(value)]

    def send(packs):
        pack, late = merge_all(packs)
        doc, start, windows = _window_runs(*late)
        yield _found(doc, start, windows)
        edge = np.searchsorted(_range_of(pack[0], ranges), np.arange(ranges + 1))
        some = [r for r in range(ranges) if edge[r] < edge[r + 1]]
        data = [np.ascontiguousarray(pack[:, edge[r] : edge[r + 1]]).tobytes() for r in some]
        n, none = len(some), pa.nulls(len(some), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(np.full(n, OPEN, np.int32)), none, none, none, pa.array(some, pa.int32()), pa.array(data, pa.binary())], ["kind", "doc", "start", "windows", "range", "pack"])

    def run(batches):
        held, size, last, packs = [], 0, None, []

        def close():
            nonlocal held, size
            gone, pack = settle(held)
            held, size = [], 0
            packs.append(pack)
            return _found(*gone)

        for batch in batches:
            shard = batch.column(1).to_numpy(zero_copy_only=False)
            new = np.flatnonzero(shard[1:] != shard[:-1]) + 1 if len(shard) else np.zeros(0, np.int64)
            for a, b in zip([0, *new], [*new, len(shard)]):
                if a == b:
                    continue
                if size >= SHARD_BYTES // 2 and shard[a] != last:
                    yield close()
                    if sum(p.shape[1] for p in packs) >= MERGED:
                        yield from send(packs)
                        packs = []
                part = batch.slice(a, b - a)
                held.append(part)
                size += int(pa.compute.sum(pa.compute.binary_length(part.column(6))).as_py())
                last = shard[a]
        if held:
            yield close()
        if any(p.shape[1] for p in packs):
            yield from send(packs)

    return strings.repartition("shard").sortWithinPartitions("shard").mapInArrow(tidy(run), _FOUND)


def _range_of(value: np.ndarray, ranges: int) -> np.ndarray:
    """The range of each value; rising with it."""
    high = (value.astype(np.float64) - float(np.iinfo(np.int64).min)) / 2.0**64
    return np.minimum((high * ranges).astype(np.int64), ranges - 1)


def _merged(packs: DataFrame) -> DataFrame:
    """(doc, start, windows) of windows that start earlier in the pack of another shard."""

    def settle(held):
        _, late = merge_all(held)
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in _window_runs(*late)], ["doc", "start", "windows"])

    def run(batches):
        held, last = [], None
        for batch in batches:
            for number, data in zip(batch.column(0).to_pylist(), batch.column(1)):
                if held and number != last:
                    yield from settle(held)
                    held = []
                held.append(np.frombuffer(data.as_buffer(), np.int64).reshape(4, -1))
                last = number
        if held:
            yield from settle(held)

    return packs.select("range", "pack").repartition("range").sortWithinPartitions("range").mapInArrow(tidy(run), "doc long, start long, windows long")


def repeated_windows(docs: DataFrame, nth: Column, again: bool, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(doc, nth, runs): runs (start, windows) of windows that also start earlier."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc"), nth.alias("nth"), "text").filter("doc is not null")
    settled = materialize(_settle_anchors(_task_stretches(rows, length, gram)), "stretches")
    windows = F.col("content").bitwiseAND(127).alias("windows")
    gone = settled.filter(F.col("kind") == GONE).select("doc", "start", windows)
    dealt = materialize(_dealt(settled.filter(F.col("kind") == OPEN).select("anchor", "content", "doc", "start", windows), length), "dealt-stretches")
    across = dealt.filter("cut").agg(F.sum("windows")).first()[0] or 0
    once = rows.dropDuplicates(["doc", "nth"]) if again else rows
    found = materialize(_shards(_bytes_of(dealt, once, length), length, 1 + across // MERGED), "shards")
    more = found.filter(F.col("kind") == GONE).select("doc", "start", "windows")
    late = _merged(found.filter(F.col("kind") == OPEN))
    every = gone.unionByName(more).unionByName(late)
    at = F.col("start").bitwiseAND((1 << _TEXT_BITS) - 1).alias("start")
    return every.groupBy("doc", F.shiftright("start", _TEXT_BITS).alias("nth")).agg(F.collect_list(F.struct(at, "windows")).alias("runs"))


def _with_runs(docs: DataFrame, length: int, gram: int) -> tuple[DataFrame, str]:
    """``docs`` with the runs to be cut in a column of a free name."""
    nth, again = identity(docs)
    runs = repeated_windows(docs, nth, again, length, gram)
    doc, number, name = (free_name(docs, n) for n in ("runs_doc", "runs_nth", "runs_cut"))
    side = runs.select(F.col("doc").alias(doc), F.col("nth").alias(number), F.col("runs").alias(name))
    return docs.join(side, (docs["doc_id"].cast("long") == F.col(doc)) & (nth == F.col(number)), "left"), name


def _gone_bytes(lists: pa.Array, row: int, n: int, length: int) -> np.ndarray | None:
    """Which of the ``n`` bytes of a text its runs cover; None without runs."""
    if not lists[row].is_valid:
        return None
    parts = lists[row].values
    a = np.minimum(parts.field("start").to_numpy(zero_copy_only=False), n)
    b = np.minimum(a + parts.field("windows").to_numpy(zero_copy_only=False) + length - 1, n)
    depth = np.zeros(n + 1, np.int32)
    np.add.at(depth, a, 1)
    np.add.at(depth, b, -1)
    return np.cumsum(depth)[:n] > 0


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """Every row of ``docs``: doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept."""
    joined, name = _with_runs(docs.select("doc_id", "text"), length, gram)

    def run(batches):
        for batch in batches:
            raw, offsets = utf8(batch.column(1))
            out = []
            for i in range(batch.num_rows):
                text = raw[offsets[i] : offsets[i + 1]]
                gone = _gone_bytes(batch.column(2), i, len(text), length)
                cut, spans = 0, 0
                if gone is not None:
                    cut = int(gone.sum())
                    spans = int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum())
                    text = text[~gone]
                data = text.tobytes()
                out.append((len(data) + cut, cut, spans, hashlib.sha256(data).hexdigest(), data))
            c = list(zip(*out))
            if c:
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(x, pa.int64()) for x in c[:3]), pa.array(c[3]), pa.array(c[4], pa.binary())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    return joined.select(F.col("doc_id").cast("long"), "text", name).mapInArrow(tidy(run), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def without_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """``docs`` with repeated passages cut from ``text``; bytes of letters cut in half go too."""
    joined, name = _with_runs(docs, length, gram)
    schema = docs.schema
    at = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            raw, offsets = utf8(batch.column(at))
            texts = batch.column(at).to_pylist()
            lists = batch.column(len(schema))
            for i in range(batch.num_rows):
                gone = _gone_bytes(lists, i, int(offsets[i + 1] - offsets[i]), length)
                if gone is not None:
                    texts[i] = raw[offsets[i] : offsets[i + 1]][~gone].tobytes().decode("utf-8", "ignore")
            columns = list(batch.columns[: len(schema)])
            columns[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays(columns, schema.names)

    return joined.select(*(docs[c] for c in docs.columns), name).mapInArrow(tidy(run), schema)
