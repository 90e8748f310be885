"""The engine from SQL: temporary functions and views over edges and features."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

FUNCTIONS = {
    "graph_relu(h ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>": "transform(h, x -> greatest(x, 0D))",
    "graph_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "graph_channels(h ARRAY<DOUBLE>, kept ARRAY<INT>) RETURNS ARRAY<DOUBLE>": "transform(kept, j -> element_at(h, j + 1))",
}


def register(spark: SparkSession) -> None:
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")


def views(edges: DataFrame, feats: DataFrame) -> None:
    """graph_edges, graph_features and their mean over neighbours, graph_mean."""
    from prunegraph.operators.propagate import propagate

    width = len(feats.first()["h"])
    edges.createOrReplaceTempView("graph_edges")
    feats.createOrReplaceTempView("graph_features")
    propagate(edges, feats, width).createOrReplaceTempView("graph_mean")
