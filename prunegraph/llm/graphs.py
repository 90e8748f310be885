"""Near-duplicate vectors by navigable small-world graphs.

Equal vectors with equal labels are collapsed. The rest of a label is spread over
shards of bounded size; each shard gets a hierarchical navigable small-world graph, kept
as a row of bytes. Every shard of a label queries every shard of it: one task takes two
shards, searches either graph with the other's members, and counts links on both ends, so
a link found from one end counts for both. An audit compares the links that sampled
members find with brute force and doubles the beam until the recall is met, in each
shard and again between shards; a sample with too few links to tell widens the beam. A
query whose whole beam is linked widens it to the whole linked region. Found pairs are
confirmed by cosine in double precision. A task returns a count per vector and the links
of a spanning forest, never a row per link; components are united from the forests.

Defined cases: rows that ``vectors.clean`` leaves out and rows with a null label link
with nothing and stand alone; vectors of different lengths are never linked; repeated
rows are copies that link with each other; empty tables give no rows; further columns
are ignored.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prunegraph.llm.common import components, materialize
from prunegraph.llm.vectors import clean, collapse, matrix

SHARD = 8192
DEGREE = 12
BEAM = 24
RECALL = 0.995
#: Members an audit looks at, at most, and links it asks for to be believed.
AUDIT, ENOUGH = 2048, 100
_ROWS = 512


def _spread(x: np.ndarray, near: np.ndarray, like: np.ndarray, m: int) -> np.ndarray:
    """Per row, up to ``m`` of the candidates ``near`` (by falling ``like``, -1 absent) such
    that none is closer to one taken before than to the row; the rest fills up."""
    n, c = near.shape
    order = np.argsort(-like, axis=1, kind="stable")
    near, like = np.take_along_axis(near, order, 1), np.take_along_axis(like, order, 1)
    v = x[np.maximum(near, 0)]
    between = np.einsum("ncd,ned->nce", v, v)
    taken = np.zeros((n, c), bool)
    for j in range(c):
        close = (between[:, j, :] > like[:, j : j + 1]) & taken
        taken[:, j] = (near[:, j] >= 0) & ~close.any(axis=1) & (taken.sum(axis=1) < m)
    rank = np.argsort(~taken, axis=1, kind="stable")[:, :m]
    out = np.take_along_axis(near, rank, 1)
    if out.shape[1] < m:
        out = np.pad(out, ((0, 0), (0, m - out.shape[1])), constant_values=-1)
    return out


class SmallWorld:
    """A graph over unit vectors; the order of insertion sets the layers."""

    def __init__(self, x: np.ndarray, degree: int = DEGREE, beam: int = BEAM, seed: int = 3):
        self.x, self.beam = np.ascontiguousarray(x, np.float32), beam
        n = len(x)
        level = np.floor(-np.log(1 - np.random.default_rng(seed).random(n)) / np.log(degree)).astype(int)
        order = np.argsort(-level, kind="stable")
        self.layers = []
        for l in range(int(level.max(initial=0)), 0, -1):
            members = np.flatnonzero(level >= l)
            self.layers.append(self._exact(members, degree))
        self.start = int(order[0]) if n else -1
        self.links = np.full((n, 2 * degree), -1, np.int32)
        self.back = None
        done = 1
        while done < n:
            new = order[done : min(n, done + max(8, min(512, done)))]
            self._insert(new, order[:done] if done < 8 else None, degree)
            done += len(new)

    def _exact(self, members: np.ndarray, degree: int):
        links = np.full((len(members), degree), -1, np.int32)
        for at in range(0, len(members), 256):
            some = members[at : at + 256]
            like = self.x[some] @ self.x[members].T
            like[np.arange(len(some)), at + np.arange(len(some))] = -2
            c = min(3 * degree, len(members) - 1)
            if c:
                best = np.argpartition(-like, c - 1, axis=1)[:, :c]
                links[at : at + 256] = _spread(self.x, members[best], np.take_along_axis(like, best, 1), degree)
        place = {int(m): i for i, m in enumerate(members)}
        at = np.full(len(self.x), -1, np.int32)
        at[list(place)] = list(place.values())
        return at, links

    def _insert(self, new: np.ndarray, few: np.ndarray | None, degree: int) -> None:
        q = self.x[new]
        if few is not None:
            near, like = np.tile(few, (len(new), 1)), q @ self.x[few].T
        else:
            near, like = self.search(q, self.beam)
        same = q @ q.T
        np.fill_diagonal(same, -2)
        c = min(degree, len(new) - 1)
        if c:
            best = np.argpartition(-same, c - 1, axis=1)[:, :c]
            near = np.concatenate([near, new[best]], 1)
            like = np.concatenate([like, np.take_along_axis(same, best, 1)], 1)
        like = np.where(near >= 0, like, -2)
        mine = _spread(self.x, near, like, degree)
        self.links[new, :degree] = mine
        source, target = np.repeat(new, mine.shape[1]), mine.ravel()
        source, target = source[target >= 0], target[target >= 0]
        order = np.argsort(target, kind="stable")
        source, target = source[order], target[order]
        nodes, first = np.unique(target, return_index=True)
        count = np.diff(np.append(first, len(target)))
        room = self.links.shape[1]
        for at in range(0, len(nodes), 1024):
            some, f, n = nodes[at : at + 1024], first[at : at + 1024], np.minimum(count[at : at + 1024], room)
            more = np.full((len(some), int(n.max())), -1, np.int64)
            for j in range(more.shape[1]):
                ok = n > j
                more[ok, j] = source[f[ok] + j]
            both = np.concatenate([self.links[some].astype(np.int64), more], 1)
            filled = (both >= 0).sum(axis=1)
            fits = filled <= room
            packed = np.take_along_axis(both, np.argsort(both < 0, axis=1, kind="stable"), 1)[:, :room]
            self.links[some[fits]] = packed[fits]
            if (~fits).any():
                full, cand = some[~fits], both[~fits]
                like = np.einsum("nd,ncd->nc", self.x[full], self.x[np.maximum(cand, 0)])
                like[cand < 0] = -2
                self.links[full] = _spread(self.x, cand, like, room)

    def _walk(self, q, layer, entry):
        """Greedy walk in an upper layer."""
        at, links = layer
        here, like = entry.copy(), np.einsum("nd,nd->n", q, self.x[entry])
        moving = np.arange(len(q))
        while len(moving):
            near = links[at[here[moving]]]
            s = np.einsum("nd,ncd->nc", q[moving], self.x[np.maximum(near, 0)])
            s[near < 0] = -2
            j = s.argmax(axis=1)
            top = s[np.arange(len(moving)), j]
            better = top > like[moving]
            moving, j, top = moving[better], j[better], top[better]
            here[moving], like[moving] = near[better][np.arange(len(moving)), j], top
        return here

    def search(self, q: np.ndarray, beam: int, entry: np.ndarray | None = None):
        """(ids, likeness) of the beam of each query, best first; -1 where short."""
        n, total = len(q), len(self.x)
        beam = min(beam, total)
        if entry is None:
            entry = np.full(n, self.start)
            for layer in self.layers:
                entry = self._walk(q, layer, entry)
        ids = np.full((n, beam), -1, np.int64)
        like = np.full((n, beam), -2.0, np.float32)
        open_ = np.zeros((n, beam), bool)
        ids[:, 0], like[:, 0], open_[:, 0] = entry, np.einsum("nd,nd->n", q, self.x[entry]), True
        seen = np.zeros((n, total), bool)
        seen[np.arange(n), entry] = True
        active = np.arange(n)
        while len(active):
            score = np.where(open_[active], like[active], -3)
            j = score.argmax(axis=1)
            go = score[np.arange(len(active)), j] > -3
            active, j = active[go], j[go]
            if not len(active):
                break
            open_[active, j] = False
            near = self.links[ids[active, j]].astype(np.int64)
            ok = near >= 0
            ok &= ~seen[active[:, None], np.maximum(near, 0)]
            seen[active[:, None], np.maximum(near, 0)] |= near >= 0
            s = np.einsum("nd,ncd->nc", q[active], self.x[np.maximum(near, 0)])
            s[~ok] = -2
            all_ids = np.concatenate([ids[active], np.where(ok, near, -1)], 1)
            all_like = np.concatenate([like[active], s], 1)
            all_open = np.concatenate([open_[active], ok], 1)
            best = np.argpartition(-all_like, beam - 1, axis=1)[:, :beam]
            ids[active], like[active], open_[active] = (np.take_along_axis(a, best, 1) for a in (all_ids, all_like, all_open))
        order = np.argsort(-like, axis=1, kind="stable")
        return np.take_along_axis(ids, order, 1), np.take_along_axis(like, order, 1)

    def linked(self, q: np.ndarray, least: float, beam: int, own: np.ndarray | None = None):
        """(query, member) pairs at or above ``least``; beams that are all linked widen."""
        rows, members = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        step = max(8, min(512, (1 << 22) // max(1, len(self.x)), (1 << 17) // beam))
        for at in range(0, len(q), step):
            some = np.arange(at, min(len(q), at + step))
            ids, like = self.search(q[some], beam, None if own is None else own[some])
            full = (like[:, -1] >= least) & (ids.shape[1] < len(self.x))
            r, c = np.nonzero((like >= least) & (ids >= 0) & ~full[:, None])
            rows.append(some[r])
            members.append(ids[r, c])
            if full.any():
                r, m = self._flood(q[some[full]], ids[full], least)
                rows.append(some[full][r])
                members.append(m)
        return np.concatenate(rows), np.concatenate(members)

    def _around(self, m: np.ndarray, who: np.ndarray):
        """Neighbours of ``m`` along links either way, with the ``who`` of each."""
        if self.back is None:
            source, target = np.repeat(np.arange(len(self.x)), self.links.shape[1]), self.links.ravel().astype(np.int64)
            source, target = source[target >= 0], target[target >= 0]
            order = np.argsort(target, kind="stable")
            self.back = source[order], np.searchsorted(target[order], np.arange(len(self.x) + 1))
        source, first = self.back
        out = self.links[m].astype(np.int64)
        size = first[m + 1] - first[m]
        n = int(size.sum())
        back = source[np.arange(n) + np.repeat(first[m] - (np.cumsum(size) - size), size)]
        there = out.ravel() >= 0
        return np.concatenate([out.ravel()[there], back]), np.concatenate([np.repeat(who, out.shape[1])[there], np.repeat(who, size)])

    def _flood(self, q: np.ndarray, ids: np.ndarray, least: float, slack: float = 0.03):
        """Widens the beam to all that is reached over members within ``slack`` of ``least``;
        every member is opened once, so the work follows the number of links."""
        n, total = len(q), len(self.x)
        seen = np.zeros((n, total), bool)
        r, m = np.repeat(np.arange(n), ids.shape[1]), ids.ravel()
        seen[r, m] = True
        rows, members = [r], [m]
        while len(r):
            next_r, next_m = [], []
            for at in range(0, len(r), 1 << 13):
                near, who = self._around(m[at : at + (1 << 13)], r[at : at + (1 << 13)])
                ok = ~seen[who, near]
                pair = np.unique(who[ok] * total + near[ok])
                who, near = pair // total, pair % total
                seen[who, near] = True
                like = np.einsum("nd,nd->n", q[who], self.x[near])
                good = like >= least
                rows.append(who[good])
                members.append(near[good])
                on = like >= least - slack
                next_r.append(who[on])
                next_m.append(near[on])
            r, m = np.concatenate(next_r), np.concatenate(next_m)
        return np.concatenate(rows), np.concatenate(members)


def audited(graph: SmallWorld, least: float, seed: int = 9) -> int:
    """The beam at which sampled members find ``RECALL`` of their links from the top.

    Links of a member to itself do not count. The sample grows until it holds ``ENOUGH``
    links; one that stays short of them proves nothing, and the beam is doubled."""
    n = len(graph.x)
    order = np.random.default_rng(seed).permutation(n)[:AUDIT]
    some, links = order[:0], 0
    truth = np.zeros((0, n), bool)
    while len(some) < len(order) and links < ENOUGH:
        more = order[len(some) : len(some) + 256]
        near = graph.x[more] @ graph.x.T >= least
        near[np.arange(len(more)), more] = False
        some, truth, links = np.concatenate([some, more]), np.concatenate([truth, near]), links + int(near.sum())
    beam = graph.beam if links >= ENOUGH else 2 * graph.beam
    at = np.flatnonzero(truth.any(axis=1))
    some, truth = some[at], truth[at]
    while links and beam < n:
        r, m = graph.linked(graph.x[some], least, beam)
        found = np.zeros_like(truth)
        found[r, m] = True
        if (found & truth).sum() >= RECALL * truth.sum():
            break
        beam *= 2
    return min(beam, n)


@dataclass
class Shard:
    """A graph with its beam, node names, unit vectors in double precision and copies."""

    graph: SmallWorld
    beam: int
    nodes: np.ndarray
    exact: np.ndarray
    copies: np.ndarray


def links_into(asking: Shard, shard: Shard, least: float, beam: int, own: bool) -> np.ndarray:
    """(asking, members) matrix of links found in ``shard`` and confirmed."""
    out = np.zeros((len(asking.exact), len(shard.exact)), bool)
    for at in range(0, len(out), _ROWS):
        q = asking.exact[at : at + _ROWS]
        r, m = shard.graph.linked(q.astype(np.float32), least - 1e-5, beam, np.arange(at, at + len(q)) if own else None)
        if 16 * len(r) > len(q) * len(shard.exact):
            found = np.zeros((len(q), len(shard.exact)), bool)
            found[r, m] = True
            out[at : at + len(q)] = found & (q @ shard.exact.T >= least)
            continue
        for k in range(0, len(r), 1 << 17):
            i, j = r[k : k + (1 << 17)], m[k : k + (1 << 17)]
            good = np.einsum("nd,nd->n", q[i], shard.exact[j]) >= least
            out[at + i[good], j[good]] = True
    return out


def links_between(a: Shard, b: Shard, least: float) -> np.ndarray:
    """Links of the members of two shards, searched from both ends and audited."""
    some = np.random.default_rng(len(a.exact)).permutation(len(a.exact))[: AUDIT // 8]
    truth = a.exact[some] @ b.exact.T >= least
    beams = [a.beam, b.beam]
    while True:
        found = links_into(a, b, least, beams[1], False)
        found |= links_into(b, a, least, beams[0], False).T
        if (found[some] & truth).sum() >= RECALL * truth.sum() or (beams[0] >= len(a.exact) and beams[1] >= len(b.exact)):
            return found
        beams = [2 * x for x in beams]


def forest(linked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) pairs that join what ``linked`` joins: all if few, else a spanning forest."""
    n = int(linked.sum())
    if n <= 2 * sum(linked.shape):
        return np.nonzero(linked)
    turned = np.ascontiguousarray(linked.T)
    fresh_rows, fresh_columns = linked.any(axis=1), linked.any(axis=0)
    rows, columns = [], []
    for seed in np.flatnonzero(fresh_rows):
        if not fresh_rows[seed]:
            continue
        fresh_rows[seed] = False
        front = np.array([seed])
        while len(front):
            reached = np.flatnonzero(linked[front].any(axis=0) & fresh_columns)
            fresh_columns[reached] = False
            rows.append(front[linked[front][:, reached].argmax(axis=0)] if len(reached) else reached)
            columns.append(reached)
            if not len(reached):
                break
            front = np.flatnonzero(turned[reached].any(axis=0) & fresh_rows)
            fresh_rows[front] = False
            rows.append(front)
            columns.append(reached[turned[reached][:, front].argmax(axis=0)] if len(front) else front)
    return np.concatenate(rows), np.concatenate(columns)


def near_vectors(vectors: DataFrame, least: float = 0.93, label: str = "label", shard: int = SHARD) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of ``vectors``."""
    rows = clean(vectors).filter(F.col(label).isNotNull()).withColumn("label", F.col(label))
    once = collapse(rows, ["label"], 1).withColumn("dim", F.size("vector"))
    once = materialize(once.select("print", "label", "dim", "vector", "rep", "n"), "distinct-vectors")
    sizes = once.groupBy("label", "dim").agg(F.ceil(F.count(F.lit(1)) / shard).cast("int").alias("shards"))
    # a node is a distinct (label, vector); 64 bits of its content name it
    node = F.xxhash64("print", "label")
    placed = once.join(sizes, ["label", "dim"]).select(
        "label", "dim", "rep", "vector", "n", "print", "shards", node.alias("node"),
        F.pmod(F.xxhash64("print"), F.col("shards")).cast("int").alias("shard"),
    )
    placed = materialize(placed, "placed-vectors")

    def build(key, table):
        x = matrix(table.column("vector"))
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        graph = SmallWorld(x)
        blob = pickle.dumps(Shard(graph, audited(graph, least - 1e-5), table.column("node").to_numpy(), x, table.column("n").to_numpy()))
        return pa.table([pa.array([v]) for v in (key[0].as_py(), key[1].as_py(), key[2].as_py(), table.column("shards")[0].as_py())] + [pa.array([blob], pa.binary())], schema=pa.schema([("label", table.schema.field("label").type), ("dim", pa.int32()), ("shard", pa.int32()), ("shards", pa.int32()), ("graph", pa.binary())]))

    kind = dict(placed.dtypes)["label"]
    graphs = placed.select("label", "dim", "shard", "shards", "vector", "node", "n").groupBy("label", "dim", "shard").applyInArrow(build, f"label {kind}, dim int, shard int, shards int, graph binary")
    graphs = materialize(graphs, "graphs")
    met = graphs.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)))
    met = met.select("label", "dim", F.least("shard", "other").alias("lo"), F.greatest("shard", "other").alias("hi"), "graph")

    def meet(key, table):
        shards = [pickle.loads(b.as_py()) for b in table.column("graph")]
        a, b = shards[0], shards[-1]
        if len(shards) == 1:
            linked = links_into(a, a, least, a.beam, True)
            linked |= linked.T
            np.fill_diagonal(linked, False)
        else:
            linked = links_between(a, b, least)
        x, y = forest(linked)
        ends = [(a, linked, b.copies)] + ([(b, linked.T, a.copies)] if len(shards) > 1 else [])
        names, degree = [], []
        for own, at, copies in ends:
            n = np.concatenate([at[k : k + _ROWS] @ copies for k in range(0, len(at), _ROWS)])
            names.append(own.nodes[n > 0])
            degree.append(n[n > 0])
        names, degree = np.concatenate(names), np.concatenate(degree)
        none = pa.nulls(len(names), pa.int64())
        return pa.table([pa.array(np.concatenate([a.nodes[x], names])), pa.concat_arrays([pa.array(b.nodes[y], pa.int64()), none]), pa.concat_arrays([pa.nulls(len(x), pa.int64()), pa.array(degree, pa.int64())])], ["a", "b", "n"])

    links = met.groupBy("label", "dim", "lo", "hi").applyInArrow(meet, "a long, b long, n long")
    links = materialize(links, "vector-links")
    degree = links.filter("b is null").groupBy(F.col("a").alias("id")).agg(F.sum("n").alias("degree"))
    names = placed.select(F.col("node").alias("id"), "rep")
    label_of = components(links.filter("b is not null").select("a", "b"), "vectors").join(names, "id")
    least_id = label_of.groupBy("component").agg(F.min("rep").alias("component_id"))
    node_rows = (
        placed.select(F.col("node").alias("id"), "rep", "n")
        .join(degree, "id", "left")
        .join(label_of.select("id", "component").join(least_id, "component").select("id", "component_id"), "id", "left")
        .select(F.col("id"), (F.coalesce("degree", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component_id", "rep").alias("component_id"))
    )
    return _back(vectors, rows, node_rows)


def _back(vectors: DataFrame, rows: DataFrame, node_rows: DataFrame) -> DataFrame:
    """Node results to every row; rows that take no part stand alone."""
    import hashlib

    def prints(batches):
        for batch in batches:
            flat, at = batch.column(1).flatten().to_numpy(zero_copy_only=False) + 0.0, batch.column(1).offsets.to_numpy()
            out = [hashlib.blake2b(flat[at[i] - at[0] : at[i + 1] - at[0]].tobytes(), digest_size=16).digest() for i in range(batch.num_rows)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary()), batch.column(2)], ["vec_id", "print", "label"])

    kind = dict(rows.dtypes)["label"]
    named = rows.select(F.col("vec_id").cast("long"), "vector", "label").mapInArrow(prints, f"vec_id long, print binary, label {kind}").select("vec_id", F.xxhash64("print", "label").alias("id"))
    found = named.join(node_rows, "id").select("vec_id", "n_links", "component_id")
    marked = vectors.withColumn("vector", F.col("embedding").cast("array<double>"))
    norm = F.aggregate(F.col("vector"), F.lit(0.0), lambda s, x: s + x * x)
    part = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & (F.size("vector") > 0) & norm.isNotNull() & ~F.isnan(norm) & (norm > 0) & (norm < float("inf"))
    alone = marked.filter(~F.coalesce(part, F.lit(False))).select(F.col("vec_id").cast("long"), F.lit(0).cast("long").alias("n_links"), F.col("vec_id").cast("long").alias("component_id"))
    every = found.unionByName(alone)
    return every.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
