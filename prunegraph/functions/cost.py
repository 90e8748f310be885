"""Cost measures: multiply-adds, bytes, support sizes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: dims: per layer (input width, {order: output width}).
Dims = list[tuple[int, dict[int, int]]]


def network_dims(net, width: int) -> Dims:
    """Widths of a network as it stands, pruned branches counted by what they read."""
    dims, w = [], width
    for layer in net.layers:
        dims.append((w, {k: x.shape[1] for k, x in layer.weights.items()}))
        w = layer.f_out
    return dims


def full_layer_macs(f_in: int, outs: dict[int, int], degree: float, order: str = "min") -> float:
    total = sum(f_in * o for o in outs.values())
    top = max(outs)
    if top:
        moved = f_in if order == "agg_first" else min(f_in, max(o for k, o in outs.items() if k))
        total += top * degree * moved
    return total


def full_macs(dims: Dims, degree: float, order: str = "min") -> float:
    """Per node, all layers."""
    return sum(full_layer_macs(f, o, degree, order) for f, o in dims)


def full_memory(dims: Dims, nodes: int) -> list[int]:
    """Per layer: values read and written for all nodes, and weights."""
    return [nodes * (f + sum(o.values())) + sum(f * x for x in o.values()) for f, o in dims]


def support_counts(degree: float, depth: int, targets: int = 1) -> list[dict[str, float]]:
    """Predicted nodes read and produced by each layer, before any overlap."""
    powers = lambda n: sum(degree**l for l in range(n + 1))
    return [{"layer": i, "produced": targets * powers(depth - i), "read": targets * powers(depth - i + 1)} for i in range(1, depth + 1)]


def batched_macs(dims: Dims, degree: float, order: str = "min") -> float:
    """Per target: each layer's cost times the nodes it produces."""
    return sum(s["produced"] * full_layer_macs(f, o, degree, order) for s, (f, o) in zip(support_counts(degree, len(dims)), dims))


def batched_bound(dims: Dims, degree: float, order: str = "min") -> float:
    """The dominating term: the first layer at the widest support."""
    return degree ** (len(dims) - 1) * full_layer_macs(*dims[0], degree, order)


def printed_full_kmacs(f: int, h: int, c: int, nodes: int, edges: int, eta: float = 1.0) -> float:
    """kMACs a node as the published tables count them (own reading of their cells)."""
    d, wide, one = 2 * edges / nodes, 2 * h * eta, h * eta
    return ((d + 1) * f + 2 * f * one + (d + 1) * wide + 2 * wide * one + wide * c + 4 * wide) / 1000


def printed_full_mib(f: int, h: int, nodes: int, edges: int, eta: float = 1.0) -> float:
    wide, one = 2 * h * eta, h * eta
    return (4 * nodes * max(f + wide, 3 * wide) + 4 * 2 * edges + 4 * max(2 * f * one, 2 * wide * one)) / 2**20


def printed_batched_kmacs(f: int, h: int, c: int, nodes: int, edges: int, cap: int = 32) -> float:
    d = 2 * edges / nodes
    return ((d + 1) * ((min(cap, d) + 1) * f + 2 * f * h + 4 * h) + (d + 1) * 2 * h + 4 * h * h + 2 * h * c + 4 * h) / 1000


def preprocess_macs(degree: float, width: int, steps: int) -> float:
    """Propagating raw attributes ``steps`` times, once."""
    return steps * degree * width


def observed_support(support: DataFrame) -> DataFrame:
    """Distinct nodes per batch, layer and role."""
    return support.groupBy("batch_id", "layer", "role").agg(F.countDistinct("node_id").alias("nodes"))


def measured_full(net, nodes: int, edges: int, width: int) -> list[dict]:
    """Multiply-adds a node of each layer of a network as it is, survivors per branch counted."""
    out, w = [], width
    for i, layer in enumerate(net.layers, start=1):
        macs = 0.0
        for k, x in layer.weights.items():
            read = len(layer.reads(k, w))
            macs += read * x.shape[1] + k * edges / nodes * min(read, x.shape[1])
        out.append({"layer": i, "macs": macs, "bytes": 4.0 * nodes * (w + layer.f_out)})
        w = layer.f_out
    if net.head is not None:
        out.append({"layer": len(net.layers) + 1, "macs": float(net.head.size), "bytes": 4.0 * nodes * (w + net.head.shape[1])})
    return out


def measured_batched(net, used: dict[int, DataFrame], support: DataFrame, width: int, targets: int) -> float:
    """Multiply-adds a target from the edges and nodes that a batched run really touched."""
    made = lambda i: support.filter((F.col("layer") == i) & (F.col("role") != "visited")).select("batch_id", "node_id").distinct().count()
    return batched_from_counts(net, {i: (used[i].count(), made(i)) for i in range(1, len(net.layers) + 1)}, width, targets)


def batched_from_counts(net, counts: dict[int, tuple[int, int]], width: int, targets: int) -> float:
    """As ``measured_batched``, from each layer's (edges, nodes produced) over all batches."""
    total, w = 0.0, width
    for i, layer in enumerate(net.layers, start=1):
        links, made = counts[i]
        for k, x in layer.weights.items():
            read = len(layer.reads(k, w))
            total += made * read * x.shape[1] + (k * links * min(read, x.shape[1]) if k else 0)
        w = layer.f_out
    if net.head is not None:
        total += targets * net.head.size
    return total / max(1, targets)


def input_bytes(support: DataFrame, width: int) -> DataFrame:
    """Bytes of raw attributes each batch reads."""
    return support.filter("layer = 0").groupBy("batch_id").agg((F.countDistinct("node_id") * 4 * width).alias("bytes"))


def store_reduction(without: DataFrame, with_store: DataFrame, layer: int = 1) -> DataFrame:
    """Share of a layer's support that stored features save."""
    n = lambda df: df.filter((F.col("layer") == layer) & (F.col("role") != "visited")).select("batch_id", "node_id").distinct().agg(F.count(F.lit(1)).alias("n"))
    return n(without).crossJoin(n(with_store).withColumnRenamed("n", "m")).select((1 - F.col("m") / F.col("n")).alias("reduction"))
