"""Layers, networks and full inference (M4-M6).

A ``Network`` is a driver-side description; running it on DataFrames builds one lazy
frame per layer. Weights are small next to the graph and travel inside the plan or
in the closure of an Arrow kernel; nodes, edges and predictions never reach the driver.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.operators.propagate import propagate_k, select_channels
from prunegraph.sources.shared import forgotten, removed, written

EXPRESSION_CELLS = 256


def formula_weights(layer: int, k: int, f_in: int, f_out: int) -> np.ndarray:
    """Dyadic weights both engines can form from the same rule."""
    j, o = np.meshgrid(np.arange(f_in), np.arange(f_out), indexing="ij")
    return (((7 * j + 3 * o + 11 * k + 5 * layer) % 9) - 4) / 8.0


def dense_product(feats: DataFrame, w: np.ndarray, column: str = "h", bias: np.ndarray | None = None) -> DataFrame:
    """h @ w for every row: expressions for small weights, one BLAS call a batch else."""
    f_in, f_out = w.shape
    rest = [c for c in feats.columns if c != column]
    if f_in * f_out <= EXPRESSION_CELLS:
        names = [f"_x{j}" for j in range(f_in)]
        cells = feats.select(*rest, *(F.col(column)[j].alias(n) for j, n in enumerate(names)))

        def total(o: int):
            parts = [F.col(n) * float(w[j, o]) for j, n in enumerate(names) if w[j, o] != 0]
            out = F.lit(0.0 if bias is None else float(bias[o]))
            for p in parts:
                out = out + p
            return out

        return cells.select(*rest, F.array(*(total(o) for o in range(f_out))).cast("array<double>").alias(column))
    import pyarrow as pa

    at = feats.columns.index(column)
    names = feats.columns

    def run(batches):
        for batch in batches:
            x = batch.column(at).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, f_in)
            y = x @ w if bias is None else x @ w + bias
            cut = pa.array(np.arange(batch.num_rows + 1, dtype=np.int32) * f_out)
            columns = list(batch.columns)
            columns[at] = pa.ListArray.from_arrays(cut, pa.array(y.ravel()))
            yield pa.RecordBatch.from_arrays(columns, names)

    schema = ", ".join(f"`{f.name}` {'array<double>' if f.name == column else f.dataType.simpleString()}" for f in feats.schema.fields)
    return feats.mapInArrow(run, schema)


def activate(h, act: str | None):
    if act is None:
        return h
    if act == "relu":
        return F.transform(h, lambda x: F.greatest(x, F.lit(0.0)))
    raise ValueError(act)


@dataclass
class GraphLayer:
    """Branches of orders k_min..k_max, each its own product, joined and activated.

    ``kept_in`` holds the input channels a pruned layer still reads, in the order of
    its weight rows; ``kept_branch`` overrides it for single branches."""

    weights: dict[int, np.ndarray]
    combine: str = "concat"
    act: str | None = "relu"
    order: str = "auto"
    residual: bool = False
    kept_in: list[int] | None = None
    kept_branch: dict[int, list[int]] = field(default_factory=dict)
    shift: dict[int, tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)  # fixed (mean, scale) per branch
    bias: np.ndarray | None = None

    @property
    def f_out(self) -> int:
        sizes = [w.shape[1] for w in self.weights.values()]
        return sum(sizes) if self.combine == "concat" else sizes[0]

    def reads(self, k: int, width: int) -> list[int]:
        return self.kept_branch.get(k, self.kept_in if self.kept_in is not None else list(range(width)))

    def forward(self, nodes: DataFrame, edges: DataFrame, feats: DataFrame, width: int, layout: str = "auto", group: str | None = None) -> DataFrame:
        keys = [group, "node_id"] if group else ["node_id"]
        frames = []
        top = max(self.weights)
        chain: dict[tuple, list[DataFrame]] = {}
        for k, w in sorted(self.weights.items()):
            kept = self.reads(k, width)
            first = self.order == "mul_first" or (self.order == "auto" and w.shape[1] < len(kept))
            x = feats if kept == list(range(width)) else select_channels(feats, kept)
            if k and first and k not in self.shift:
                x = dense_product(x, w)
                y = propagate_k(edges, x, k, w.shape[1], nodes, layout=layout, group=group)[k]
            else:
                key = tuple(kept)
                if key not in chain:
                    chain[key] = propagate_k(edges, x, max((q for q in self.weights if tuple(self.reads(q, width)) == key), default=top), len(kept), nodes, layout=layout, group=group)
                y = chain[key][k]
                if k in self.shift:
                    mean, scale = self.shift[k]
                    y = dense_product(y, w / scale[:, None], bias=-(mean / scale) @ w)
                else:
                    y = dense_product(y, w)
            frames.append(y.select(*keys, F.col("h").alias(f"h{k}")))
        out = nodes.select(*keys)
        for y in frames:
            out = out.join(y, keys)
        parts = [f"h{k}" for k in sorted(self.weights)]
        if self.combine == "concat":
            h = F.concat(*parts) if len(parts) > 1 else F.col(parts[0])
        else:
            h = F.col(parts[0])
            for p in parts[1:]:
                h = F.zip_with(h, F.col(p), lambda a, b: a + b)
            h = F.transform(h, lambda x: x / len(parts))
        if self.bias is not None:
            h = F.zip_with(h, F.array(*(F.lit(float(b)) for b in self.bias)), lambda a, b: a + b)
        h = activate(h, self.act)
        out = out.select(*keys, h.alias("h"))
        if self.residual:
            out = out.join(feats.select(*keys, F.col("h").alias("old")), keys).select(*keys, F.zip_with("h", "old", lambda a, b: a + b).alias("h"))
        return out


@dataclass
class AttentionLayer:
    """Every head is a branch: softmax over a node's neighbours of leaky(a . [Wh | Wh'])."""

    heads: list[tuple[np.ndarray, np.ndarray, np.ndarray]]  # (W, for dst, for src)
    act: str | None = "relu"
    slope: float = 0.2
    scores: list[tuple[np.ndarray, np.ndarray]] | None = None  # per head, over input channels
    kept_in: list[int] | None = None  # input channels a pruned layer reads

    @property
    def f_out(self) -> int:
        return sum(w.shape[1] for w, _, _ in self.heads)

    def score_of(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        w, a_dst, a_src = self.heads[i]
        return self.scores[i] if self.scores else (w @ a_dst, w @ a_src)

    def mixed_inputs(self, nodes, edges, feats, width) -> list[DataFrame]:
        """Per head, every node's inputs mixed by that head's attention (no weights, no activation)."""
        out = []
        for i in range(len(self.heads)):
            u, v = self.score_of(i)
            plain = AttentionLayer([(np.eye(width), u, v)], act=None, slope=self.slope, scores=[(u, v)])
            out.append(plain.forward(nodes, edges, feats, width))
        return out

    def forward(self, nodes, edges, feats, width, layout="auto", group=None) -> DataFrame:
        """Every head in one pass over the edges, which meet both ends once each.

        Joins are by sorting: the sides are as long as the graph has nodes, so none is broadcast."""
        keys = [group] if group else []
        if self.kept_in is not None:
            feats = select_channels(feats, self.kept_in)
        n, sizes = len(self.heads), [w.shape[1] for w, _, _ in self.heads]
        f = sum(sizes)
        ends = [self.score_of(i) for i in range(n)]
        if not keys and hasattr(edges, "_blocks"):
            return self._by_blocks(nodes, edges, feats, ends)
        z = dense_product(feats.select(*keys, "node_id", "h"), np.concatenate([*(w for w, _, _ in self.heads), *(d[:, None] for d, _ in ends), *(s[:, None] for _, s in ends)], 1))
        there = z.select(*keys, F.col("node_id").alias("src"), *(F.col("h")[j].alias(f"x{j}") for j in range(f)), *(F.col("h")[f + n + i].alias(f"s{i}") for i in range(n)))
        here = z.select(*keys, F.col("node_id").alias("dst"), *(F.col("h")[f + i].alias(f"d{i}") for i in range(n)))
        e = edges.select(*keys, "dst", "src").join(there.hint("merge"), [*keys, "src"]).join(here.hint("merge"), [*keys, "dst"])
        raw = [F.col(f"d{i}") + F.col(f"s{i}") for i in range(n)]
        e = e.select(*keys, "dst", *(f"x{j}" for j in range(f)), *(F.when(r > 0, r).otherwise(r * self.slope).alias(f"e{i}") for i, r in enumerate(raw)))
        # rows of a dst stand together after the join, so its largest score needs no further exchange
        near = Window.partitionBy(*keys, "dst")
        e = e.select(*keys, "dst", *(f"x{j}" for j in range(f)), *(F.exp(F.col(f"e{i}") - F.max(f"e{i}").over(near)).alias(f"w{i}") for i in range(n)))
        of = [i for i, size in enumerate(sizes) for _ in range(size)]
        total = e.groupBy(*keys, "dst").agg(*(F.sum(f"w{i}").alias(f"t{i}") for i in range(n)), *(F.sum(F.col(f"w{of[j]}") * F.col(f"x{j}")).alias(f"c{j}") for j in range(f)))
        mixed = total.select(*keys, F.col("dst").alias("node_id"), F.array(*(F.col(f"c{j}") / F.col(f"t{of[j]}") for j in range(f))).alias("h"))
        out = nodes.select(*keys, "node_id").join(mixed.hint("merge"), [*keys, "node_id"], "left")
        return out.select(*keys, "node_id", activate(F.coalesce("h", F.array_repeat(F.lit(0.0), f)), self.act).alias("h"))

    def _by_blocks(self, nodes, edges, feats, ends) -> DataFrame:
        """Edges of ``blocked``: a head at a time, each written, so the sent features of one are on disk at once."""
        out, steps = nodes.select("node_id"), []
        for i, ((w, _, _), (d, s)) in enumerate(zip(self.heads, ends)):
            z = dense_product(feats.select("node_id", "h"), np.concatenate([w, s[:, None], d[:, None]], 1))
            steps.append(written(edges._blocks.attention(z, w.shape[1], self.slope), "head"))
            forgotten()
            mixed = steps[-1].select("node_id", F.col("h").alias(f"h{i}"))
            out = out.join(mixed.hint("merge"), "node_id", "left").withColumn(f"h{i}", F.coalesce(f"h{i}", F.array_repeat(F.lit(0.0), w.shape[1])))
        out = out.select("node_id", activate(F.concat(*(f"h{i}" for i in range(len(steps)))), self.act).alias("h"))
        out._steps = steps
        return out


@dataclass
class Network:
    layers: list
    readout: str = "last"  # or concat_all: every layer's output side by side
    head: np.ndarray | None = None
    head_bias: np.ndarray | None = None
    head_kept: list[int] | None = None

    def copy(self) -> "Network":
        return Network([replace(l) for l in self.layers], self.readout, self.head, self.head_bias, self.head_kept)


def infer_full(net: Network, nodes: DataFrame, edges: DataFrame, feats: DataFrame, width: int, layout: str = "auto", keep_layers: bool = False, persist: bool = False):
    """Embeddings (or scores, with a head) of every node; optionally all layer outputs.

    ``persist`` writes each layer, which the next one reads once per branch; the result
    names them in ``_layers``, for ``removed`` once it has been read."""
    outputs, h, w, steps = [], feats, width, []
    for layer in net.layers:
        h = layer.forward(nodes, edges, h, w, layout=layout)
        w, own = layer.f_out, getattr(h, "_steps", [])
        h = written(h.select("node_id", "h"), "layer") if persist else h
        if persist:
            removed(*own)
        else:
            steps += own
        outputs.append((h, w))
    if net.readout == "concat_all":
        out = nodes.select("node_id")
        for i, (x, _) in enumerate(outputs):
            out = out.join(x.select("node_id", F.col("h").alias(f"o{i}")), "node_id")
        h = out.select("node_id", F.concat(*(f"o{i}" for i in range(len(outputs)))).alias("h"))
        w = sum(x for _, x in outputs)
    if net.head is not None:
        if net.head_kept is not None:
            h = select_channels(h, net.head_kept)
        h = dense_product(h, net.head, bias=net.head_bias)
    h._layers = [x for x, _ in outputs] if persist else steps
    return (h, [(feats, width), *outputs]) if keep_layers else h


def predictions(scores: DataFrame, multilabel: bool = False) -> DataFrame:
    """The largest score's class (least on ties), or the positive classes."""
    if multilabel:
        return scores.withColumn("pred", F.transform("h", lambda x: x > 0))
    return scores.withColumn("pred", (F.array_position("h", F.array_max("h")) - 1).cast("int"))


def random_weights(rng: np.random.Generator, f_in: int, f_out: int) -> np.ndarray:
    return rng.standard_normal((f_in, f_out)) * np.sqrt(2.0 / (f_in + f_out))


class presets:
    """Architectures by their orders; weights come from ``make(layer, k, f_in, f_out)``."""

    @staticmethod
    def _stack(k_min, k_max, widths, make, combine="concat", acts=None):
        layers, f_in = [], widths[0]
        for i, f_out in enumerate(widths[1:], start=1):
            layer = GraphLayer({k: make(i, k, f_in, f_out) for k in range(k_min, k_max + 1)}, combine=combine, act="relu" if acts is None else acts[i - 1])
            layers.append(layer)
            f_in = layer.f_out
        return Network(layers)

    @staticmethod
    def convolution(widths, make=formula_weights):
        return presets._stack(1, 1, widths, make)

    @staticmethod
    def self_and_mean(widths, make=formula_weights):
        return presets._stack(0, 1, widths, make)

    @staticmethod
    def multi_order(k_max, widths, make=formula_weights):
        return presets._stack(0, k_max, widths, make)

    @staticmethod
    def dense(widths, make=formula_weights, acts=None):
        return presets._stack(0, 0, widths, make, acts=acts)

    @staticmethod
    def averaged(k_min, k_max, widths, make=formula_weights):
        return presets._stack(k_min, k_max, widths, make, combine="mean")

    @staticmethod
    def jumping(widths, make=formula_weights):
        net = presets.self_and_mean(widths, make)
        net.readout = "concat_all"
        return net
