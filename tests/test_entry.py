"""Every registered query against DuckDB at the smallest size."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from prunegraph import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES = sorted(catalog.oracle_sql())


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", QUERIES)
def test_query_equals_sql(spark, small, duck, name):
    df = entry.queries()[name](spark, small)
    mine = sorted((tuple(r[c] for c in sorted(df.columns)) for r in df.collect()), key=repr)
    found = duck.execute(entry.oracle_sql()[name])
    names = [d[0] for d in found.description]
    order = sorted(range(len(names)), key=lambda i: names[i])
    theirs = sorted((tuple(r[i] for i in order) for r in found.fetchall()), key=repr)
    assert sorted(df.columns) == sorted(names) and mine == theirs


def test_entry(spark):
    assert entry.entry(spark).columns == ["node_id", "ch", "v"]


@pytest.mark.parametrize("name", ["cost_rollup", "mask_clip", "printed_costs", "random_select", "weight_norm_select"])
def test_query_follows_its_table(spark, small, tmp_path, name):
    """Results come from a given table: other rows give other results."""
    import os

    from prunegraph.plans import measures

    for t in ("customer", "part", "supplier", "orders", "lineitem", "embeddings"):
        if t not in ("customer", "embeddings"):
            os.symlink(f"{small}/{t}.parquet", f"{tmp_path}/{t}.parquet")
    spark.read.parquet(f"{small}/customer.parquet").filter("c_custkey < 20").write.parquet(f"{tmp_path}/customer.parquet")
    spark.read.parquet(f"{small}/embeddings.parquet").withColumn("embedding", F.slice("embedding", 1, 24)).write.parquet(f"{tmp_path}/embeddings.parquet")
    run = measures.queries()[name]
    a, b = (sorted(map(repr, run(spark, f).collect())) for f in (small, str(tmp_path)))
    assert a and b and a != b
