"""Streaming operators run over whole tables in batch mode, where they have SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from dnfblock.operators.blocking import index
from dnfblock.queries import twins
from dnfblock.queries.catalogue import query, table
from dnfblock.queries.indexing import S1
from dnfblock.sources import datasets
from dnfblock.sources.datasets import P1
from dnfblock.streaming import streams


@query("blocks_tumbling_events", "SELECT time_bucket(INTERVAL '1 hour', ts) AS window_start, event_type AS key, count(*) AS n FROM events GROUP BY ALL")
def blocks_tumbling_events(spark, d):
    return streams.block_growth(table(spark, d, "events"), "event_type")


@query("blocks_sliding_events", """SELECT time_bucket(INTERVAL '30 minutes', ts) - INTERVAL '30 minutes' * k AS window_start, event_type AS key, count(*) AS n
    FROM events, range(2) AS r(k) GROUP BY ALL""")  # fmt: skip
def blocks_sliding_events(spark, d):
    return streams.block_growth(table(spark, d, "events"), "event_type", size="1 hour", slide="30 minutes")


@query("blocks_session_events", """WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL '30 minutes' OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g)
    SELECT min(ts) AS window_start, user_id AS key, count(*) AS n FROM s GROUP BY user_id, sid""")  # fmt: skip
def blocks_session_events(spark, d):
    return streams.block_sessions(table(spark, d, "events"), "user_id")


@query("stream_static_candidates_p1", f"""WITH {twins.sides(P1)}, lk AS ({twins.key_rows(S1, 0, 'l')}), rk AS ({twins.key_rows(S1, 1, 'r')})
    SELECT lk.rid AS l_rid, rk.rid AS r_rid, CAST(term AS INTEGER) AS term_id, key FROM lk JOIN rk USING (term, key)""")  # fmt: skip
def stream_static_candidates_p1(spark, d):
    left, right, _ = datasets.load(spark, d, P1)
    return streams.stream_candidates_static(left, right, S1)


@query("merge_property_table_events", """SELECT CAST(user_id AS VARCHAR) AS s, event_type AS p, CAST(count(DISTINCT cast(round(value * 100) as bigint)) AS BIGINT) AS n FROM events GROUP BY ALL""")
def merge_property_table_events(spark, d):
    e = table(spark, d, "events").select("event_id", F.col("user_id").cast("string").alias("s"), F.col("event_type").alias("p"), F.expr("cast(cast(round(value * 100) as bigint) as string)").alias("o"))
    old = e.where("event_id % 3 <> 0").groupBy("s", "p").agg(F.collect_set("o").alias("values"))
    merged = streams.merge_property_table(old, e.where("event_id % 3 = 0"))
    return merged.select("s", "p", F.size("values").cast("long").alias("n"))


@query("index_sizes_p1", f"WITH {twins.sides(P1)} SELECT CAST(term AS INTEGER) AS term_id, count(*) AS n_keys FROM ({twins.key_rows(S1, 1, 'r')}) GROUP BY term")
def index_sizes_p1(spark, d):
    return index(datasets.side(spark, d, P1.right), S1, 1).groupBy("term_id").agg(F.count("*").alias("n_keys"))
