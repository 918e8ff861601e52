"""Streaming queries over `events`, drained once; their SQL works on the table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.maps import identity_map
from ..operators.sketch import long_form
from ..plans.registry import Registry
from ..sources.tables import event_stream, load_table
from .sketches import SketchStore, drained, drift_alarms, rocksdb_state, windowed

R = Registry()
FX = "CAST(floor((value / 100) * 1048576.0::DOUBLE + 0.5) AS BIGINT)"


def featured(df: DataFrame) -> DataFrame:
    return df.withColumn("features", F.array(F.col("value") / 100))


def _out(df: DataFrame, keys: list[str]) -> DataFrame:
    start = F.date_format(F.col("w.start"), "yyyy-MM-dd HH:mm:ss").alias("start")
    return df.select(start, *keys, "n", F.get("acc_fx", F.lit(0)).cast("bigint").alias("acc_fx"))


@R.add("stream_tumbling", f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, CAST(sum({FX}) AS BIGINT) AS acc_fx FROM events GROUP BY 1, 2")
def _(s: SparkSession, d: str) -> DataFrame:
    return _out(drained(windowed(featured(event_stream(s, d)), identity_map(1), F.window("ts", "1 day"), keys=("event_type",)), "complete"), ["event_type"])


@R.add("stream_sliding", f"WITH w AS (SELECT unnest(range(4)) AS k, value, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01') AS b FROM events) SELECT strftime(b - k * INTERVAL 6 HOUR, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, CAST(sum({FX}) AS BIGINT) AS acc_fx FROM w GROUP BY 1")
def _(s, d):
    return _out(drained(windowed(featured(event_stream(s, d)), identity_map(1), F.window("ts", "1 day", "6 hours")), "complete"), [])


@R.add("stream_session", f"WITH o AS (SELECT user_id, ts, value, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS b FROM events), g AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM o) SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n, CAST(sum({FX}) AS BIGINT) AS acc_fx FROM g GROUP BY user_id, g")
def _(s, d):
    # a session for almost every event: neither the state nor the result may live in a heap
    with rocksdb_state(s):
        return _out(drained(windowed(featured(event_stream(s, d)), identity_map(1), F.session_window("ts", "30 minutes"), keys=("user_id",)), "complete"), ["user_id"])


@R.add("stream_append_closed", f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, CAST(sum({FX}) AS BIGINT) AS acc_fx FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY 1")
def _(s, d):
    return _out(drained(windowed(featured(event_stream(s, d)), identity_map(1), F.window("ts", "1 day")), "append"), [])


@R.add("stream_dedup", "SELECT count(*) AS n FROM events")
def _(s, d):
    e = event_stream(s, d).withWatermark("ts", "1 hour")
    twice = e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return drained(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "append").agg(F.count(F.lit(1)).alias("n"))


@R.add("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def _(s, d):
    c = load_table(s, d, "customer").select("c_custkey", "c_mktsegment")
    j = event_stream(s, d).join(c, F.col("user_id") == F.col("c_custkey"))
    return drained(j.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "complete")


@R.add("stream_interval_join", "SELECT a.event_id AS signup, b.event_id AS follow FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'signup' AND b.event_type = 'purchase'")
def _(s, d):
    a = event_stream(s, d).where("event_type = 'signup'").select(F.col("event_id").alias("signup"), F.col("user_id").alias("u"), F.col("ts").alias("t1")).withWatermark("t1", "1 hour")
    b = event_stream(s, d).where("event_type = 'purchase'").select(F.col("event_id").alias("follow"), "user_id", F.col("ts").alias("t2")).withWatermark("t2", "1 hour")
    return drained(a.join(b, (F.col("u") == F.col("user_id")) & (F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr("INTERVAL 6 HOURS"))).select("signup", "follow"), "append")


@R.add("stream_retract", f"SELECT event_type AS dataset_id, CAST(sum(CASE WHEN event_id % 7 = 0 THEN -1 ELSE 1 END) AS BIGINT) AS n, 0 AS j, CAST(sum(CASE WHEN event_id % 7 = 0 THEN -1 ELSE 1 END * {FX}) AS BIGINT) AS acc_fx FROM events GROUP BY 1")
def _(s, d):
    store = SketchStore(s, identity_map(1))
    rows = featured(event_stream(s, d)).withColumn("op", F.when(F.pmod("event_id", F.lit(7)) == 0, -1).otherwise(1))
    store.run(rows, "event_type")
    return long_form(store.state())


@R.add("stream_redecode", "SELECT true AS ok")
def _(s, d):
    store = SketchStore(s, identity_map(1))
    got = store.run(featured(event_stream(s, d)), None, 1, lambda sk: sk.first().acc[0] / sk.first().n)
    want = load_table(s, d, "events").agg(F.avg(F.col("value") / 100)).first()[0]
    return s.createDataFrame([(bool(abs(got[-1] - want) < 1e-9),)], "ok boolean")


@R.add("stream_late", "SELECT count(*) AS kept FROM events")
def _(s, d):
    # late rows within the watermark are kept: one batch holds them all, so none is beyond it
    e = event_stream(s, d).withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return drained(e, "complete").agg(F.sum("n").alias("kept"))


@R.add("stream_drift_alarm", "SELECT CAST(event_type AS VARCHAR) AS key, count(*) AS n FROM events GROUP BY 1")
def _(s, d):
    with rocksdb_state(s):
        out = drained(drift_alarms(featured(event_stream(s, d)), "event_type", 0.5), "update")
    return out.groupBy("key").agg(F.max("n").alias("n"))


@R.add("stream_equals_batch", "SELECT true AS ok")
def _(s, d):
    from ..operators.sketch import mean_sketch

    store = SketchStore(s, identity_map(1))
    store.run(featured(event_stream(s, d)), "event_type")
    a, b = long_form(store.state()), long_form(mean_sketch(featured(load_table(s, d, "events")), identity_map(1), "event_type"))
    return a.exceptAll(b).unionAll(b.exceptAll(a)).agg((F.count(F.lit(1)) == 0).alias("ok"))


