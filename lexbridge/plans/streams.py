"""Registered streaming queries, each drained over the events table; oracles say what the batch would."""

from __future__ import annotations

from pyspark.sql import functions as F

from lexbridge.plans.frames import ALPHA
from lexbridge.sources.tables import table
from lexbridge.streaming import bank as S

QUERIES, ORACLES = {}, {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle
        return f

    return add


@query(f"""WITH t AS (SELECT event_type AS word, CASE WHEN user_id % 2 = 0 THEN 'S' ELSE 'T' END AS side, CASE WHEN value > 50 THEN 1 ELSE -1 END AS label, ts, event_id FROM events),
r AS (SELECT *, count(*) OVER (PARTITION BY word, side) - row_number() OVER (PARTITION BY word, side ORDER BY ts, event_id) AS later FROM t)
SELECT word, side, count(*) AS n, sum({1 - ALPHA!r} * label * pow({ALPHA}, later)) AS p FROM r GROUP BY ALL""")
def wl_stream_bank(spark, sf_dir):
    out = S.drain(S.stream_bank(S.tokens(S.event_stream(spark, sf_dir)), ALPHA), "update")
    return out.groupBy("word", "side").agg(F.max("n").alias("n"), F.max_by("p", "n").alias("p"))


@query("SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def op_stream_complete(spark, sf_dir):
    return S.drain(S.event_stream(spark, sf_dir).groupBy("event_type").agg(F.count("*").alias("n")), "complete")


@query("SELECT time_bucket(INTERVAL 1 DAY, ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def op_stream_tumbling(spark, sf_dir):
    e = S.event_stream(spark, sf_dir).withWatermark("ts", "1 hour")
    out = S.drain(e.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n")), "complete")
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("day"), "event_type", "n")


@query()
def op_stream_sliding(spark, sf_dir):
    e = S.event_stream(spark, sf_dir).withWatermark("ts", "1 hour")
    out = S.drain(e.groupBy(F.window("ts", "1 day", "12 hours")).agg(F.avg("value").alias("mean")), "complete")
    return out.select(F.col("window.start").alias("start"), "mean")


@query()
def op_stream_session(spark, sf_dir):
    e = S.event_stream(spark, sf_dir).withWatermark("ts", "1 hour")
    out = S.drain(e.groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n")), "complete")
    return out.select(F.col("session_window.start").alias("start"), "user_id", "n")


@query("SELECT count(DISTINCT event_id) AS n FROM events")
def op_stream_dedup(spark, sf_dir):
    e = S.event_stream(spark, sf_dir).withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_id"])
    return S.drain(e.select("event_id")).agg(F.count("*").alias("n"))


@query("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def op_stream_static_join(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    e = S.event_stream(spark, sf_dir)
    return S.drain(e.join(c, e.user_id == c.c_custkey).select("event_id", "c_mktsegment"))


@query("SELECT p.event_id, v.event_id AS seen FROM events p JOIN events v ON p.user_id = v.user_id AND v.ts BETWEEN p.ts - INTERVAL 1 HOUR AND p.ts WHERE p.event_type = 'purchase' AND v.event_type = 'view'")
def op_stream_interval_join(spark, sf_dir):
    e = S.event_stream(spark, sf_dir).select("event_id", "user_id", "event_type", "ts")
    p = e.where("event_type = 'purchase'").withWatermark("ts", "400 days")
    v = e.where("event_type = 'view'").select(F.col("event_id").alias("seen"), F.col("user_id").alias("u"), F.col("ts").alias("at")).withWatermark("at", "400 days")
    met = p.join(v, F.expr("user_id = u and at between ts - interval 1 hour and ts"))
    return S.drain(met.select("event_id", "seen"))
