"""The operators around the methods: joins, windows, sets, strings, time, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.operators import edges as E
from prunegraph.operators.propagate import from_wide, select_channels, to_wide
from prunegraph.plans.headline import WIDTH, base, cells, fixed_column
from prunegraph.sources.shared import shared_folder
from prunegraph.sources.tables import node_ids, read, validate_edges, validate_features
from prunegraph.streaming import scorer


def spam_half_hour(spark, folder):
    """Arrivals of the timestamped task by half hour."""
    e = read(spark, folder, "events")
    slot = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 1800)
    return e.groupBy(slot.cast("long").alias("slot")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("user_id").alias("users"))


def spam_daily(spark, folder):
    """Per day: events, those on documents of low quality, the busiest half hour."""
    docs = read(spark, folder, "labels").filter("quality is not null").select("doc_id", "quality")
    n = docs.agg(F.count(F.lit(1)).alias("docs"))
    ranked = docs.withColumn("r", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("doc_id")) - 1)
    e = read(spark, folder, "events").crossJoin(F.broadcast(n)).withColumn("r", F.pmod("event_id", F.col("docs")))
    rows = e.join(ranked, "r").withColumn("day", F.to_date("ts")).withColumn("slot", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 1800))
    slots = rows.groupBy("day", "slot").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("quality") == 0).cast("long")).alias("spam"))
    return slots.groupBy("day").agg(F.sum("n").alias("events"), F.sum("spam").alias("spam"), F.max("n").alias("busiest"))


def session_users(spark, folder):
    """Sessions of a user with a six-hour gap."""
    e = read(spark, folder, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    s = e.groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
    return s.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


def asof_store(spark, folder):
    """For every event, the latest earlier event of the user of type 'purchase' (as-of join)."""
    e = read(spark, folder, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.select("event_id", last.alias("asof_id"))


def _streamed(spark, stream, mode):
    name = f"stream_{uuid.uuid4().hex}"
    return scorer.run_to_table(stream, name, f"{shared_folder(spark)}/{name}", mode=mode)


def stream_half_hour(spark, folder):
    """The half-hour counts by Structured Streaming over the same events."""
    out = _streamed(spark, scorer.half_hours(scorer.event_stream(spark, folder)), "complete")
    return out.select((F.unix_timestamp("window.start") / 1800).cast("long").alias("slot"), "n")


def stream_sliding(spark, folder):
    """Events of a type in every day-long window that starts on the hour."""
    out = _streamed(spark, scorer.sliding_days(scorer.event_stream(spark, folder)), "complete")
    return out.select((F.unix_timestamp("window.start") / 3600).cast("long").alias("hour"), "event_type", "n")


def stream_sessions(spark, folder):
    """Sessions of a user with a six-hour gap, by Structured Streaming."""
    out = _streamed(spark, scorer.user_sessions(scorer.event_stream(spark, folder)), "complete")
    return out.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


def stream_follow_ups(spark, folder):
    """Purchases within a day after a click of the same user (stream-stream join)."""
    return _streamed(spark, scorer.follow_ups(scorer.event_stream(spark, folder), "click", "purchase", "1 day"), "append")


def stream_segments(spark, folder):
    """Arriving events by the market segment of their user (stream-static join)."""
    c = read(spark, folder, "customer").select("c_custkey", "c_mktsegment")
    rows = scorer.with_static(scorer.event_stream(spark, folder), c, "c_custkey")
    return _streamed(spark, rows.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "complete")


def stream_user_state(spark, folder):
    """Per user: events, the latest one and the largest value, kept in state."""
    out = _streamed(spark, scorer.user_state(scorer.event_stream(spark, folder)), "update")
    last = out.groupBy("user_id").agg(F.max_by(F.struct("n", "last_id", "most"), "n").alias("s"))
    return last.select("user_id", "s.n", "s.last_id", "s.most")


def duplicate_report(spark, folder):
    lines = read(spark, folder, "lineitem").select(F.col("l_orderkey").alias("dst"), F.col("l_partkey").alias("src"))
    return validate_edges(lines)


def feature_report(spark, folder):
    rows = read(spark, folder, "embeddings").select(F.col("vec_id").alias("node_id"), F.col("embedding").cast("array<double>").alias("h"))
    return validate_features(rows, 64)


def split_counts(spark, folder):
    return node_ids(spark, folder).groupBy(E.split_of().alias("split")).agg(F.count(F.lit(1)).alias("n"))


def inductive_edges(spark, folder):
    nodes = node_ids(spark, folder)
    return E.inside(E.purchase(spark, folder), nodes.filter(E.split_of() == "train"))


def visited_split(spark, folder):
    """Neighbours of test nodes that are stored (semi join) and not (anti join)."""
    nodes, edges, _ = base(spark, folder)
    test = nodes.filter(E.split_of() == "test").select(F.col("node_id").alias("dst"))
    near = edges.join(test, "dst", "left_semi").select(F.col("src").alias("node_id")).distinct()
    kept = nodes.filter(E.split_of() == "train")
    yes, no = near.join(kept, "node_id", "left_semi"), near.join(kept, "node_id", "left_anti")
    return yes.agg(F.count(F.lit(1)).alias("visited")).crossJoin(no.agg(F.count(F.lit(1)).alias("unvisited")))


def outer_isolated(spark, folder):
    """Customers without and with orders (outer join)."""
    c = read(spark, folder, "customer").select("c_custkey")
    o = read(spark, folder, "orders").select("o_custkey").distinct()
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "full").groupBy(F.col("o_custkey").isNull().alias("isolated")).agg(F.count(F.lit(1)).alias("n"))


def region_broadcast(spark, folder):
    """Customers a region: two dimension tables of fixed size broadcast."""
    n, r = read(spark, folder, "nation"), read(spark, folder, "region")
    return read(spark, folder, "customer").select("c_nationkey").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


def quantile_labels(spark, folder):
    """Quartile of a customer's mean order total."""
    m = read(spark, folder, "orders").groupBy("o_custkey").agg(F.avg("o_totalprice").alias("m"))
    return m.select("o_custkey", F.ntile(4).over(Window.partitionBy(F.lit(0)).orderBy(fixed_column(F.col("m")), "o_custkey")).alias("quartile"))


def running_edges(spark, folder):
    """Orders of a customer so far, and days since the one before."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    o = read(spark, folder, "orders")
    return o.select("o_orderkey", F.row_number().over(w).alias("nth"), F.datediff("o_orderdate", F.lag("o_orderdate").over(w)).alias("gap_days"))


def set_operations(spark, folder):
    """Parts bought and delivered: union, intersection, difference."""
    a = E.purchase(spark, folder).filter("dst % 4 = 1").select(F.col("dst").alias("n")).distinct()
    b = E.supply(spark, folder).filter("dst % 4 = 1").select(F.col("dst").alias("n")).distinct()
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("what"), "n")
    return count(a.union(b).distinct(), "union").unionByName(count(a.intersect(b), "intersection")).unionByName(count(a.exceptAll(b), "difference"))


def event_json(spark, folder):
    """Values of the JSON key by event type."""
    k = F.from_json("props", "map<string,int>")["k"]
    return read(spark, folder, "events").groupBy("event_type").agg(F.count(k).alias("n"), F.sum(k).cast("long").alias("total"), F.max(k).alias("most"))


def type_pivot(spark, folder):
    """Order status by priority, pivoted."""
    return read(spark, folder, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("o_orderpriority", *(F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "FOP"))


def grouping_cube(spark, folder):
    o = read(spark, folder, "orders")
    return o.cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


def hash_sample(spark, folder):
    from prunegraph.operators.support import hash_of

    return node_ids(spark, folder).filter(hash_of() < 16384)


def channel_gather(spark, folder):
    nodes, _, feats = base(spark, folder)
    return cells(select_channels(feats, [5, 0, 3]))


def wide_round_trip(spark, folder):
    nodes, _, feats = base(spark, folder)
    return cells(from_wide(to_wide(feats, WIDTH), WIDTH))


def edge_scores(spark, folder):
    """Dot products of vectors along the neighbour graph: an edge head."""
    v = read(spark, folder, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("h"))
    g = E.nearest_vectors(spark, folder).join(v.select(F.col("vec_id").alias("dst"), F.col("h").alias("a")), "dst").join(v.select(F.col("vec_id").alias("src"), F.col("h").alias("b")), "src")
    return g.select("dst", "src", fixed_column(F.aggregate(F.zip_with("a", "b", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)).alias("score"))


def graph_pool(spark, folder):
    """Mean of a node set's features by kind: a graph head."""
    _, _, feats = base(spark, folder)
    m = feats.groupBy(F.pmod("node_id", F.lit(4)).alias("kind")).agg(*(F.avg(F.col("h")[j]).alias(f"m{j}") for j in range(3)))
    return m.select("kind", *(fixed_column(F.col(f"m{j}")).alias(f"m{j}") for j in range(3)))


def sql_surface(spark, folder):
    """Own and neighbour features of a node compared, all from SQL."""
    from prunegraph.functions import sql

    _, edges, feats = base(spark, folder)
    sql.register(spark)
    sql.views(edges, feats)
    return spark.sql("SELECT node_id, CAST(floor(graph_dot(graph_channels(f.h, array(0, 2)), graph_relu(graph_channels(m.h, array(0, 2)))) * 1000000 + 0.4999) AS BIGINT) AS v FROM graph_features f JOIN graph_mean m USING (node_id)")


def queries() -> dict:
    return {f.__name__: f for f in (
        spam_half_hour, spam_daily, session_users, asof_store, stream_half_hour, stream_sliding, stream_sessions, stream_follow_ups, stream_segments, stream_user_state, duplicate_report, feature_report, split_counts, inductive_edges, visited_split, outer_isolated,
        region_broadcast, quantile_labels, running_edges, set_operations, event_json, type_pivot, grouping_cube, hash_sample, channel_gather, wide_round_trip, edge_scores, graph_pool, sql_surface,
    )}


def oracle_sql() -> dict[str, str]:
    from prunegraph.plans.sqltext import GRAPHS, NODES, SPLIT, Plan, fixed

    slot = "CAST(floor(epoch(ts) / 1800) AS BIGINT)"
    split = SPLIT.format(n="node_id")
    graph = lambda body, g="purchase": Plan(g).select(body)
    sessions = """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g),
c AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2) SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1"""
    half = f"SELECT {slot} AS slot, count(*) AS n FROM events GROUP BY 1"

    def features(body):
        p = Plan()
        f = p.features(WIDTH)
        return p.select(body.format(f=f))

    buy = graph("SELECT DISTINCT dst AS n FROM e WHERE dst % 4 = 1")
    sup = graph("SELECT DISTINCT dst AS n FROM e WHERE dst % 4 = 1", "supply")
    surface = Plan()
    own = surface.features(WIDTH)
    near = surface.step(own)
    return {
        "sql_surface": surface.select(f"SELECT o.node_id, {fixed('sum(o.x * greatest(n.x, 0))')} AS v FROM {own} o JOIN {near} n ON n.node_id = o.node_id AND n.j = o.j WHERE o.j IN (0, 2) AND o.node_id IN (SELECT dst FROM e) GROUP BY 1"),
        "spam_half_hour": f"SELECT {slot} AS slot, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1",
        "stream_half_hour": half,
        "spam_daily": f"""WITH d AS (SELECT doc_id, quality, row_number() OVER (ORDER BY doc_id) - 1 AS r FROM labels WHERE quality IS NOT NULL),
s AS (SELECT CAST(ts AS DATE) AS day, {slot} AS slot, count(*) AS n, sum((quality = 0)::INT) AS spam FROM events JOIN d ON d.r = event_id % (SELECT count(*) FROM d) GROUP BY 1, 2)
SELECT day, CAST(sum(n) AS BIGINT) AS events, CAST(sum(spam) AS BIGINT) AS spam, max(n) AS busiest FROM s GROUP BY 1""",
        "session_users": sessions,
        "stream_sessions": sessions,
        "stream_sliding": "SELECT CAST(h - k AS BIGINT) AS hour, event_type, count(*) AS n FROM (SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS h, event_type FROM events), range(24) r(k) GROUP BY 1, 2",
        "stream_follow_ups": "SELECT b.user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY",
        "stream_segments": "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON c_custkey = user_id GROUP BY 1",
        "stream_user_state": "SELECT user_id, count(*) AS n, arg_max(event_id, (ts, event_id)) AS last_id, max(value) AS most FROM events GROUP BY 1",
        "asof_store": "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS asof_id FROM events",
        "duplicate_report": "SELECT CAST(sum((n > 1)::INT) AS BIGINT) AS duplicate_pairs, CAST(sum((a = b)::INT) AS BIGINT) AS self_edges, CAST(sum((a IS NULL OR b IS NULL)::INT) AS BIGINT) AS null_ends FROM (SELECT l_orderkey AS a, l_partkey AS b, count(*) AS n FROM lineitem GROUP BY 1, 2)",
        "feature_report": "SELECT CAST(sum((len(embedding) <> 64)::INT) AS BIGINT) AS ragged, CAST(sum((embedding IS NULL)::INT) AS BIGINT) AS missing, CAST(0 AS BIGINT) AS not_finite FROM embeddings",
        "split_counts": f"WITH {NODES} SELECT CASE WHEN {split} < 60 THEN 'train' WHEN {split} < 75 THEN 'val' ELSE 'test' END AS split, count(*) AS n FROM nodes GROUP BY 1",
        "inductive_edges": graph(f"SELECT dst, src FROM e WHERE dst IN (SELECT node_id FROM nodes WHERE {split} < 60) AND src IN (SELECT node_id FROM nodes WHERE {split} < 60)"),
        "visited_split": graph(f"SELECT count(*) FILTER (s < 60) AS visited, count(*) FILTER (s >= 60) AS unvisited FROM (SELECT DISTINCT src, {SPLIT.format(n='src')} AS s FROM e WHERE {SPLIT.format(n='dst')} >= 75)"),
        "outer_isolated": "SELECT o IS NULL AS isolated, count(*) AS n FROM customer FULL JOIN (SELECT DISTINCT o_custkey AS o FROM orders) ON o = c_custkey GROUP BY 1",
        "region_broadcast": "SELECT r_name, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY 1",
        "quantile_labels": f"SELECT o_custkey, CAST(ntile(4) OVER (ORDER BY {fixed('m')}, o_custkey) AS INTEGER) AS quartile FROM (SELECT o_custkey, avg(o_totalprice) AS m FROM orders GROUP BY 1)",
        "running_edges": "SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) AS nth, CAST(CAST(o_orderdate AS DATE) - CAST(lag(o_orderdate) OVER w AS DATE) AS INTEGER) AS gap_days FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)",
        "set_operations": f"SELECT 'union' AS what, count(*) AS n FROM (({buy}) UNION ({sup})) UNION ALL SELECT 'intersection', count(*) FROM (({buy}) INTERSECT ({sup})) UNION ALL SELECT 'difference', count(*) FROM (({buy}) EXCEPT ({sup}))",
        "event_json": "SELECT event_type, count(k) AS n, CAST(sum(k) AS BIGINT) AS total, max(k) AS most FROM (SELECT event_type, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events) GROUP BY 1",
        "type_pivot": "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1",
        "grouping_cube": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
        "hash_sample": f"WITH {NODES} SELECT node_id FROM nodes WHERE ((node_id % 65536) * 40503) % 65536 < 16384",
        "channel_gather": features(f"SELECT node_id, CAST(CASE j WHEN 5 THEN 0 WHEN 0 THEN 1 ELSE 2 END AS INTEGER) AS ch, {fixed('x')} AS v FROM {{f}} WHERE j IN (0, 3, 5)"),
        "wide_round_trip": features(f"SELECT node_id, j AS ch, {fixed('x')} AS v FROM {{f}}"),
        "edge_scores": f"WITH {GRAPHS['knn']} SELECT dst, src, dot AS score FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY dot DESC, src) r FROM d) WHERE r <= 8",
        "graph_pool": features("SELECT node_id % 4 AS kind, " + ", ".join(f"CAST(floor(avg(x) FILTER (j = {j}) * 1000000 + 0.4999) AS BIGINT) AS m{j}" for j in range(3)) + " FROM {f} GROUP BY 1"),
    }
