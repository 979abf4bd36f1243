"""Small queries that show the operators around the methods: joins in time, cubes, windows, sets, pivots, JSON, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient import oracles as O
from dagquotient.functions.lineage import cut
from dagquotient.operators.maintain import renamed
from dagquotient.sources import fixtures
from dagquotient.sources.tables import load, sql_over
from dagquotient.streaming import events as stream

_REF = O.ctes("reference")
_KIND = "node_id // 100000000000000 AS kind"


def _kinds(spark: SparkSession, d: str) -> DataFrame:
    return fixtures.graph(spark, d, "reference").nodes.select(F.expr("node_id div 100000000000000").alias("kind"), "label")


def _latest_view(spark: SparkSession, d: str) -> DataFrame:
    """As-of join of each event with the last one of its user's views before it, by a window."""
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)
    return load(spark, d, "events").select("event_id", F.coalesce(seen, F.lit(-1)).alias("view_id"))


def _set_op(which: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        a, b = (fixtures.graph(spark, d, g).edges.select("parent", "child") for g in ("random", "two_tier"))
        return a.intersect(b) if which == "intersect" else a.subtract(b)

    return run


def _edge_sql(which: str) -> str:
    a, b = (O.ctes(g).removeprefix("WITH RECURSIVE ") for g in ("random", "two_tier"))
    return f"WITH {a.replace('n AS', 'n1 AS', 1).replace(', e AS', ', e1 AS', 1)}, {b.replace('n AS', 'n2 AS', 1).replace(', e AS', ', e2 AS', 1)} SELECT parent, child FROM e1 {which} SELECT parent, child FROM e2"


def _stamp(c) -> object:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


def _sliding(events: DataFrame) -> DataFrame:
    return events.groupBy(F.window("ts", "1 day", "6 hours").alias("w"), "event_type").agg(F.count("*").alias("n")).select(_stamp(F.col("w.start")).alias("since"), "event_type", "n")


_SLIDING = """SELECT strftime(time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') - k * INTERVAL '6 hours', '%Y-%m-%d %H:%M:%S') AS since, event_type, count(*) AS n
FROM events, range(0, 4) r(k) GROUP BY ALL"""
_SESSIONS = """SELECT user_id, session::BIGINT AS session, count(*) AS n FROM (
  SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (
    SELECT *, (coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL '6 hours', true))::INT AS fresh FROM events)) GROUP BY ALL"""
_LAGS = "coalesce(lag(event_type, 2) OVER w, '#') || '/' || coalesce(lag(event_type, 1) OVER w, '#') || '/' || event_type"


def _sessions(spark: SparkSession, d: str) -> DataFrame:
    found = load(spark, d, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    nth = F.row_number().over(Window.partitionBy("user_id").orderBy("w.start")).cast("long")
    return found.select("user_id", nth.alias("session"), "n")


def _stream_days(spark: SparkSession, d: str) -> DataFrame:
    found = stream.counted(stream.source(spark, f"{d.rstrip('/')}/events*.parquet"), F.window("ts", "1 day"), "event_type")
    return found.select(F.col("window.start").cast("date").alias("day"), "event_type", "n")


def _events(spark: SparkSession, d: str) -> DataFrame:
    return stream.source(spark, f"{d.rstrip('/')}/events*.parquet")


def _stream_indexed(spark: SparkSession, d: str) -> DataFrame:
    """Turns of conversations with the turn after each as its child, from files that a stream reads."""
    g = fixtures.graph(spark, d, "conversation")
    told = g.edges.groupBy(F.col("parent").alias("node_id")).agg(F.collect_list("child").alias("children"))
    arrivals = cut(g.nodes.join(told, "node_id", "left").select("node_id", "label", F.coalesce("children", F.array().cast("array<long>")).alias("children")))
    folder = arrivals.inputFiles()[0].rsplit("/", 1)[0]
    return renamed(cut(stream.indexed(spark.readStream.schema(arrivals.schema).parquet(folder))))


def _block_ranks(spark: SparkSession, d: str) -> DataFrame:
    sizes = _kinds(spark, d).groupBy("kind", "label").agg(F.count("*").alias("n"))
    w = Window.partitionBy("kind").orderBy(F.desc("n"), "label")
    return sizes.select("kind", "label", "n", F.rank().over(Window.partitionBy("kind").orderBy(F.desc("n"))).cast("long").alias("place"), F.dense_rank().over(Window.partitionBy("kind").orderBy(F.desc("n"))).cast("long").alias("dense"), F.ntile(4).over(w).cast("long").alias("quarter"))


QUERIES = {
    "as_of_view": (_latest_view, "SELECT event_id, coalesce(last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS view_id FROM events"),
    "cube_labels": (lambda s, d: _kinds(s, d).cube("kind", "label").agg(F.count("*").alias("n")), f"{_REF} SELECT kind, label, count(*) AS n FROM (SELECT {_KIND}, label FROM n) GROUP BY CUBE (kind, label)"),
    "grouping_sets_events": (lambda s, d: sql_over(s, d, "SELECT user_id, event_type, count(*) AS n FROM {events} GROUP BY GROUPING SETS ((user_id), (event_type), ())"), "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY GROUPING SETS ((user_id), (event_type), ())"),
    "window_ranks": (_block_ranks, f"{_REF}, z AS (SELECT {_KIND}, label, count(*) AS n FROM n GROUP BY ALL) SELECT kind, label, n, rank() OVER w AS place, dense_rank() OVER w AS dense, ntile(4) OVER (PARTITION BY kind ORDER BY n DESC, label) AS quarter FROM z WINDOW w AS (PARTITION BY kind ORDER BY n DESC)"),
    "except_edges": (_set_op("except"), _edge_sql("EXCEPT")),
    "intersect_edges": (_set_op("intersect"), _edge_sql("INTERSECT")),
    "pivot_segments": (lambda s, d: load(s, d, "customer").groupBy("c_nationkey").pivot("c_mktsegment", ["BUILDING", "MACHINERY"]).agg(F.count(F.lit(1))).na.fill(0), "SELECT c_nationkey, count(*) FILTER (WHERE c_mktsegment = 'BUILDING') AS BUILDING, count(*) FILTER (WHERE c_mktsegment = 'MACHINERY') AS MACHINERY FROM customer GROUP BY c_nationkey"),
    "json_labels": (lambda s, d: load(s, d, "events").groupBy((F.get_json_object("props", "$.k").cast("long") % 10).alias("bucket")).agg(F.count("*").alias("n")), "SELECT (props::JSON ->> '$.k')::BIGINT % 10 AS bucket, count(*) AS n FROM events GROUP BY 1"),
    "array_label_paths": (lambda s, d: load(s, d, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), "/").alias("labels"), F.count("*").alias("n")), "SELECT user_id, array_to_string(list_sort(list(DISTINCT event_type)), '/') AS labels, count(*) AS n FROM events GROUP BY user_id"),
    "sliding_events": (lambda s, d: _sliding(load(s, d, "events")), _SLIDING),
    "session_events": (_sessions, _SESSIONS),
    "stream_tumbling_events": (_stream_days, "SELECT ts::DATE AS day, event_type, count(*) AS n FROM events GROUP BY ALL"),
    "stream_events_ak2": (lambda s, d: stream.traces(stream.source(s, f"{d.rstrip('/')}/events*.parquet"), 2), f"SELECT event_id AS node_id, {_LAGS} AS trace FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)"),
    "stream_near_edges": (lambda s, d: stream.near_edges(_events(s, d), _events(s, d), ("view", "purchase"), "12 hours"), "SELECT b.event_id AS parent, a.event_id AS child FROM events a JOIN events b USING (user_id) WHERE a.event_type = 'view' AND b.event_type = 'purchase' AND a.ts <= b.ts AND a.ts >= b.ts - INTERVAL '12 hours'"),
    "stream_edges_once": (lambda s, d: stream.edges_once(_events(s, d).select(F.col("user_id").alias("parent"), F.ascii("event_type").cast("long").alias("child"), "ts")).select("parent", "child"), "SELECT DISTINCT user_id AS parent, ascii(event_type)::BIGINT AS child FROM events"),
    "stream_indexed_conversation": (_stream_indexed, O.forward(O.ctes("conversation"), 12)),
}
