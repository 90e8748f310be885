import pytest
from corpus_samples import DOCS, ODD


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty and very long texts, ties, repeated rows, and columns with clashing names."""
    from pyspark.sql import functions as F

    df = spark.createDataFrame(ODD, DOCS)
    return df.withColumn("key", F.lit(1)).withColumn("id", F.lit("x")).withColumn("shard", F.lit(2)).withColumn("row", F.lit(3)).withColumn("fit", F.lit(True)).withColumn("runs", F.lit("y")).persist()


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], DOCS)
