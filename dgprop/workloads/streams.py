"""Streams that run over all events and are read back."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.operators import graph as G
from dgprop.operators.filters import FilterSpec
from dgprop.operators.propagate import PushResult
from dgprop.plans.lineage import ensure_checkpoint_dir
from dgprop.sources import tables as T
from dgprop.streaming.events import LastSeen, event_stream, run_to_table
from dgprop.streaming.updater import StreamUpdater
from dgprop.workloads import sqltext as q
from dgprop.workloads.graphs import random_x
from dgprop.workloads.registry import long_form, query, sql_r

_HOUR = 3_600_000_000
_US = "CAST(unix_micros({}) AS BIGINT)"


def _windowed(stream: DataFrame, window) -> DataFrame:
    counted = stream.withWatermark("ts", "1 hour").groupBy(window.alias("w")).agg(F.count("*").alias("n"))
    return counted.select(F.unix_micros("w.start").alias("start_us"), "n")


@query(f"SELECT epoch_us(ts) // {q.DAY} * {q.DAY} AS start_us, count(*) AS n FROM events GROUP BY 1")
def st_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_to_table(_windowed(event_stream(spark, sf_dir), F.window("ts", "1 day")), "complete")


@query(f"SELECT s AS start_us, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // {q.DAY // 2} * {q.DAY // 2}, (epoch_us(ts) // {q.DAY // 2} - 1) * {q.DAY // 2}]) AS s FROM events) GROUP BY 1")
def st_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_to_table(_windowed(event_stream(spark, sf_dir), F.window("ts", "1 day", "12 hours")), "complete")


@query(f"WITH e AS (SELECT user_id, epoch_us(ts) AS t FROM events), b AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t) < {12 * _HOUR} THEN 0 ELSE 1 END AS fresh FROM e), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t) AS k FROM b) SELECT user_id, min(t) AS start_us, count(*) AS n FROM s GROUP BY user_id, k")
def st_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "12 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return run_to_table(s.select("user_id", F.unix_micros("w.start").alias("start_us"), "n"), "complete")


@query("SELECT event_id, user_id FROM events")
def st_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event comes twice."""
    s = event_stream(spark, sf_dir)
    twice = s.union(s).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return run_to_table(twice.select("event_id", "user_id"))


@query(f"WITH a AS (SELECT event_id, user_id, epoch_us(ts) AS t FROM events WHERE event_type = 'click'), b AS (SELECT event_id, user_id, epoch_us(ts) AS t FROM events WHERE event_type = 'purchase') SELECT a.event_id AS click, b.event_id AS purchase FROM a JOIN b ON a.user_id = b.user_id AND b.t > a.t AND b.t <= a.t + {6 * _HOUR}")
def st_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = event_stream(spark, sf_dir)
    a = s.filter("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 hour")
    b = s.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("v"), F.col("ts").alias("s")).withWatermark("s", "1 hour")
    return run_to_table(a.join(b, F.expr("u = v AND s > t AND s <= t + INTERVAL 6 HOURS")).select("click", "purchase"))


@query("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE 1 = 0 UNION ALL SELECT event_id, event_type FROM events WHERE user_id IN (SELECT c_custkey FROM customer WHERE c_nationkey < 5)")
def st_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    known = T.table(spark, sf_dir, "customer").filter("c_nationkey < 5").select(F.col("c_custkey").alias("user_id"))
    s = event_stream(spark, sf_dir).join(known, "user_id", "left_semi")
    return run_to_table(s.select(F.col("event_id").alias("c_custkey"), F.col("event_type").alias("n_name")))


@query("SELECT user_id, count(*) AS n, max(event_id) AS last FROM events GROUP BY 1")
def st_stateful_last(spark: SparkSession, sf_dir: str) -> DataFrame:
    old = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        s = event_stream(spark, sf_dir).groupBy("user_id").transformWithStateInPandas(LastSeen(), "user_id bigint, n bigint, last bigint", "Update", "None")
        return run_to_table(s, "update")
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", old)


_SPEC, _RMAX = FilterSpec.restart(0.5), 1e-11


@query(q.series(q.EVENT_EDGES, 1, "", 0.5, 0.5, 48, select=f"SELECT node, dim, {sql_r(f'sum(v * ({q.geometric(0.5, 0.5)}))', 5)} AS z FROM t GROUP BY node, dim"))
def st_foreachbatch_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three batches, the second of them replayed and the third late; the state is that of all events."""
    ensure_checkpoint_dir(spark)
    events = T.interactions(spark, sf_dir).withColumn("step", G.bucket())
    path = f"{spark.sparkContext.getCheckpointDir()}/updater-{uuid.uuid4().hex}"
    update = StreamUpdater(path, random_x(events, 1), [_SPEC], _RMAX, 1)
    for batch_id, rest in ((0, 0), (1, 2), (1, 2), (2, 1)):
        update(events.filter(F.col("seq") % 3 == rest), batch_id)
    return long_form(PushResult(update.state(), [_SPEC], 1).readout(), "node", places=5)


_ROWS = f"SELECT *, CAST(ts_us // {q.DAY} AS INTEGER) AS step FROM ({q.EVENTS})"
_IN_TIME = f"""SELECT src, dst, w FROM (WITH e AS ({_ROWS}), a AS (SELECT max(step) AS m FROM e WHERE seq % 3 = 0),
    b AS (SELECT greatest(max(a.m), coalesce(max(CASE WHEN seq % 3 = 2 AND step >= a.m THEN step END), 0)) AS m FROM e, a)
    SELECT e.* FROM e, a, b WHERE seq % 3 = 0 OR (seq % 3 = 2 AND step >= a.m) OR (seq % 3 = 1 AND step >= b.m))"""
_EVERY_NODE = f"SELECT src AS node FROM ({q.EVENTS}) UNION SELECT dst FROM ({q.EVENTS})"


@query(q.series(q.edges_of(_IN_TIME), 1, "", 0.5, 0.5, 48, _EVERY_NODE, None, f"SELECT node, dim, {sql_r(f'sum(v * ({q.geometric(0.5, 0.5)}))', 5)} AS z FROM t GROUP BY node, dim"))
def st_late_drop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same batches, where events of steps before the last one that was seen are left out."""
    ensure_checkpoint_dir(spark)
    events = T.interactions(spark, sf_dir).withColumn("step", G.bucket())
    path = f"{spark.sparkContext.getCheckpointDir()}/updater-{uuid.uuid4().hex}"
    update = StreamUpdater(path, random_x(events, 1), [_SPEC], _RMAX, 1, late="drop")
    for batch_id, rest in ((0, 0), (1, 2), (2, 1)):
        update(events.filter(F.col("seq") % 3 == rest), batch_id)
    return long_form(PushResult(update.state(), [_SPEC], 1).readout(), "node", places=5)
