"""Late rows, repeated rows and state across micro-batches; sinks and formats."""

import datetime as dt
import os
import uuid

import pytest
from pyspark.sql import functions as F

from prunegraph.plans import surround
from prunegraph.plans.headline import base
from prunegraph.sources import tables
from prunegraph.streaming import scorer

FIELDS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def at(day, hour=0, minute=0):
    return dt.datetime(2024, 1, day, hour, minute)


def arrivals(spark, folder, parts):
    """A stream that sees one list of rows a micro-batch, in order."""
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, FIELDS).coalesce(1).write.parquet(f"{folder}/raw{i}")
        part = next(f for f in os.listdir(f"{folder}/raw{i}") if f.endswith(".parquet"))
        os.makedirs(f"{folder}/in", exist_ok=True)
        os.rename(f"{folder}/raw{i}/{part}", f"{folder}/in/events{i}.parquet")
        os.utime(f"{folder}/in/events{i}.parquet", (1_700_000_000 + 60 * i,) * 2)
    return scorer.event_stream(spark, f"{folder}/in")


def collected(spark, tmp_path, stream, mode):
    name = f"t_{uuid.uuid4().hex}"
    return scorer.run_to_table(stream, name, f"{tmp_path}/check", mode=mode).collect()


def test_late_rows_leave_closed_windows_alone(spark, tmp_path):
    # a micro-batch drops by the watermark that the batch before it began with
    late = [
        [(1, at(1), 1, "click", 1.0, None), (2, at(5), 1, "click", 1.0, None)],
        [(6, at(4, 23, 50), 1, "click", 1.0, None)],
        [(3, at(1, 0, 5), 1, "click", 1.0, None), (4, at(5, 0, 10), 1, "click", 1.0, None)],
        [(5, at(9), 1, "click", 1.0, None)],
    ]
    rows = collected(spark, tmp_path, scorer.half_hours(arrivals(spark, tmp_path, late)), "append")
    assert {r["window"]["start"].day: r["n"] for r in rows} == {1: 1, 4: 1, 5: 2}


def test_repeated_events_across_batches(spark, tmp_path):
    parts = [[(1, at(1), 1, "click", 1.0, None), (2, at(1), 1, "click", 1.0, None)], [(2, at(1), 1, "click", 1.0, None), (3, at(1), 2, "click", 1.0, None)]]
    rows = collected(spark, tmp_path, scorer.distinct_events(arrivals(spark, tmp_path, parts)), "append")
    assert sorted(r["event_id"] for r in rows) == [1, 2, 3]


def test_user_state_across_batches(spark, tmp_path):
    parts = [
        [(1, at(1), 1, "click", 4.0, None), (2, at(2), 1, "click", None, None), (7, at(2), None, "click", 1.0, None)],
        [(3, at(2), 1, "click", 3.0, None), (4, at(2), 2, "click", None, None), (5, None, 2, "click", 9.0, None)],
    ]
    rows = collected(spark, tmp_path, scorer.user_state(arrivals(spark, tmp_path, parts)), "update")
    latest = {}
    for r in sorted(rows, key=lambda r: r["n"]):
        latest[r["user_id"]] = (r["n"], r["last_id"], r["most"])
    assert latest == {1: (3, 3, 4.0), 2: (2, 4, 9.0), None: (1, 7, 1.0)}


def test_old_user_state_times_out(spark, tmp_path):
    parts = [[(1, at(1), 1, "click", 4.0, None)], [(2, dt.datetime(2024, 8, 1), 2, "click", 1.0, None)], [(3, dt.datetime(2024, 8, 2), 3, "click", 1.0, None)], [(4, dt.datetime(2024, 8, 2), 1, "click", 2.0, None)]]
    rows = collected(spark, tmp_path, scorer.user_state(arrivals(spark, tmp_path, parts)), "update")
    assert sorted((r["user_id"], r["n"], r["last_id"], r["most"]) for r in rows) == [(1, 1, 1, 4.0), (1, 1, 4, 2.0), (2, 1, 2, 1.0), (3, 1, 3, 1.0)]


def test_follow_ups_across_batches(spark, tmp_path):
    parts = [[(1, at(1), 1, "click", 1.0, None), (2, at(1), 2, "click", 1.0, None)], [(3, at(1, 0, 59), 1, "purchase", 1.0, None), (4, at(1, 2), 2, "purchase", 1.0, None)]]
    rows = collected(spark, tmp_path, scorer.follow_ups(arrivals(spark, tmp_path, parts), "click", "purchase"), "append")
    assert [tuple(r) for r in rows] == [(1, 1, 3)]


@pytest.mark.parametrize("kind", ["parquet", "orc", "csv", "json"])
def test_edges_survive_every_format(spark, small, tmp_path, kind):
    _, edges, _ = base(spark, small)
    tables.write(edges, f"{tmp_path}/{kind}", kind)
    back = tables.read_as(spark, f"{tmp_path}/{kind}", kind, "dst long, src long")
    assert back.exceptAll(edges).count() == 0 and edges.exceptAll(back).count() == 0


def test_partitioned_writes_are_pruned(spark, small, tmp_path):
    _, _, feats = base(spark, small)
    tables.write(feats.withColumn("layer", F.pmod("node_id", F.lit(4)).cast("int")), f"{tmp_path}/f", partition_by=["layer"])
    one = tables.read_as(spark, f"{tmp_path}/f").filter("layer = 1")
    assert one.count() == feats.filter("node_id % 4 = 1").count()
    assert "PartitionFilters: [isnotnull(layer" in one._jdf.queryExecution().executedPlan().toString()


def test_formats_without_types_need_a_schema(spark, tmp_path):
    with pytest.raises(ValueError):
        tables.read_as(spark, str(tmp_path), "csv")


def test_bucketed_edges_join_without_a_shuffle(spark, small, tmp_path):
    _, edges, _ = base(spark, small)
    name = f"edges_{uuid.uuid4().hex[:8]}"
    tables.write_bucketed(edges, name, ["dst"], 4, path=f"{tmp_path}/b")
    try:
        b = spark.table(name)
        plan = b.join(b.groupBy("dst").count().hint("merge"), "dst")
        text = plan._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in text and plan.count() == edges.count()
    finally:
        spark.sql(f"DROP TABLE {name}")


def test_plans_of_surrounding_queries(spark, small):
    text = lambda f: f(spark, small)._jdf.queryExecution().executedPlan().toString()
    assert text(surround.region_broadcast).count("BroadcastHashJoin") == 2
    assert "ReadSchema: struct<props:string,event_type:string>" in text(surround.event_json) or "ReadSchema: struct<event_type:string,props:string>" in text(surround.event_json)
    assert all("Python" not in text(f) for f in (surround.spam_half_hour, surround.asof_store, surround.graph_pool, surround.sql_surface))


@pytest.mark.parametrize("mode", ["complete", "update"])
def test_stream_rows_stay_with_the_executors(spark, tmp_path, mode):
    parts = [[(1, at(1), 1, "click", 1.0, None)], [(2, at(1), 2, "click", 1.0, None)]]
    counts = arrivals(spark, tmp_path, parts).groupBy("user_id").count()
    found = scorer.run_to_table(counts, f"t_{uuid.uuid4().hex}", f"{tmp_path}/check", mode=mode)
    assert sorted(map(tuple, found.collect())) == [(1, 1), (2, 1)]
    # written by tasks: a memory table would hold every row on the driver
    assert found.inputFiles()


def test_stream_without_rows(spark, tmp_path):
    counts = arrivals(spark, tmp_path, [[]]).groupBy("user_id").count()
    found = scorer.run_to_table(counts, f"t_{uuid.uuid4().hex}", f"{tmp_path}/check", mode="complete")
    assert found.columns == ["user_id", "count"] and found.count() == 0
