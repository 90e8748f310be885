"""The store of middle-layer features of visited nodes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.operators.support import hash_of


def latest(rows: DataFrame) -> DataFrame:
    """The last written row of each (layer, node_id, model)."""
    w = Window.partitionBy("layer", "node_id", "model").orderBy(F.desc("written_at"), F.desc("batch"))
    return rows.withColumn("_r", F.row_number().over(w)).filter("_r = 1").drop("_r")


def expire(rows: DataFrame, now, max_age: str) -> DataFrame:
    """Rows not older than ``max_age`` (an interval such as "7 days") at ``now``."""
    return rows.filter(F.col("written_at") >= now - F.expr(f"interval {max_age}"))


def choose(rows: DataFrame, policy: str | float) -> DataFrame:
    """none, all, or a share of nodes by hash; "roots" is decided by what is put."""
    if policy == "none":
        return rows.limit(0)
    if policy in ("all", "roots"):
        return rows
    return rows.filter(hash_of() < F.lit(float(policy) * 65536))


@dataclass
class FeatureStore:
    """Appends Parquet by layer and model; a batch number makes repeated writes harmless."""

    spark: object
    path: str
    model: str = "reference"

    def put(self, layer: int, feats: DataFrame, written_at, batch: int) -> None:
        rows = feats.select(F.lit(layer).alias("layer"), F.lit(self.model).alias("model"), F.lit(batch).cast("long").alias("batch"), "node_id", "h", F.lit(written_at).cast("timestamp").alias("written_at"))
        rows.write.mode("overwrite").parquet(f"{self.path}/layer={layer}/model={self.model}/batch={batch}")

    def get(self, before_batch: int | None = None) -> DataFrame | None:
        jvm = self.spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(self.path)
        if not where.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf()).exists(where):
            return None
        schema = "node_id long, h array<double>, written_at timestamp, layer int, model string, batch long"
        rows = self.spark.read.schema(schema).parquet(self.path).filter(F.col("model") == self.model)
        return latest(rows if before_batch is None else rows.filter(F.col("batch") < before_batch))


def adaptive_share(share: float, latency_ms: float, target_ms: float, drop: float, max_drop: float, step: float = 0.1) -> float:
    """Next stored share: more while latency allows, less once accuracy falls too far."""
    if drop > max_drop:
        return max(0.0, share - 2 * step)
    return min(1.0, share + step) if latency_ms < target_ms else max(0.0, share - step)
