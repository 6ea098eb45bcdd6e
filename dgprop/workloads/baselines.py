"""Baselines: those that a hash makes repeatable are checked in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.baselines import aggregates as A
from dgprop.baselines import neural as N
from dgprop.functions.hashing import sql_hash32
from dgprop.operators import graph as G
from dgprop.sources import tables as T
from dgprop.workloads import sqltext as q
from dgprop.workloads.graphs import daily, event_edges, random_x
from dgprop.workloads.registry import long_form, query, r, sql_r

_N = f"SELECT src AS node FROM ({q.EVENT_EDGES}) GROUP BY src"
_X = q.features(_N, 2)
_W = [[0.5, -0.3], [0.2, 0.8]]


def _wide(sql: str) -> str:
    return f"SELECT node, max(CASE WHEN dim = 0 THEN x END) AS x0, max(CASE WHEN dim = 1 THEN x END) AS x1 FROM ({sql}) GROUP BY node"


_BASE = f"WITH e AS ({q.EVENT_EDGES}), x AS ({_wide(_X)})"


@query(
    f"""{_BASE}, l AS (SELECT src, dst, w FROM e UNION ALL SELECT node, node, 1.0 FROM x), d AS (SELECT src AS node, sum(w) AS d FROM l GROUP BY src),
    s AS (SELECT l.dst AS node, sum(w * x0 / sqrt(d)) AS s0, sum(w * x1 / sqrt(d)) AS s1 FROM l JOIN x ON x.node = l.src JOIN d ON d.node = l.src GROUP BY l.dst),
    z AS (SELECT s.node, [greatest(0.0, (s0 * {_W[0][0]} + s1 * {_W[1][0]}) / sqrt(d)), greatest(0.0, (s0 * {_W[0][1]} + s1 * {_W[1][1]}) / sqrt(d))] AS z FROM s JOIN d USING (node))
    SELECT node, CAST(dim AS INTEGER) AS dim, {sql_r('z[dim + 1]')} AS z FROM z, range(2) AS r(dim)"""
)
def bl_conv_layer(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    return long_form(A.conv_layer(e, random_x(e, 2), _W), "node")


_DRAW = sql_hash32("concat('0:', src, ':', dst)")


@query(
    f"""{_BASE}, k AS (SELECT src, dst FROM e QUALIFY row_number() OVER (PARTITION BY src ORDER BY {_DRAW}, dst) <= 10), m AS (SELECT src AS node, avg(x0) AS m0, avg(x1) AS m1 FROM k JOIN x ON x.node = k.dst GROUP BY src),
    z AS (SELECT node, [x0, x1, m0, m1] AS z FROM x JOIN m USING (node)) SELECT node, CAST(dim AS INTEGER) AS dim, {sql_r('z[dim + 1]')} AS z FROM z, range(4) AS r(dim)"""
)
def bl_sampled_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    return long_form(A.sampled_mean(e, random_x(e, 2), 10, 2), "node")


@query(
    f"""{_BASE}, s AS (SELECT src, dst, xs.x0, xs.x1, 0.7 * xs.x0 - 0.4 * xs.x1 + 0.3 * xd.x0 + 0.9 * xd.x1 AS raw FROM e JOIN x AS xs ON xs.node = src JOIN x AS xd ON xd.node = dst),
    a AS (SELECT *, CASE WHEN raw > 0 THEN raw ELSE 0.2 * raw END AS a FROM s), z AS (SELECT dst AS node, [sum(exp(a) * x0) / sum(exp(a)), sum(exp(a) * x1) / sum(exp(a))] AS z FROM a GROUP BY dst)
    SELECT node, CAST(dim AS INTEGER) AS dim, {sql_r('z[dim + 1]')} AS z FROM z, range(2) AS r(dim)"""
)
def bl_attention_agg(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    return long_form(A.attention(e, random_x(e, 2), [0.3, 0.9], [0.7, -0.4]), "node")


@query(f"WITH e AS ({q.EVENTS}) SELECT a.seq AS query_id, CAST(row_number() OVER w AS INTEGER) AS rank, b.dst AS partner, a.ts_us - b.ts_us AS age_us, {sql_r('cos((a.ts_us - b.ts_us) / 3.6e9)')} AS code FROM e AS a JOIN e AS b ON a.src = b.src AND b.ts_us < a.ts_us WINDOW w AS (PARTITION BY a.seq ORDER BY b.ts_us DESC, b.seq DESC) QUALIFY row_number() OVER w <= 3")
def bl_recent_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = T.interactions(spark, sf_dir)
    found = A.recent_neighbours(e, e.select(F.col("seq").alias("query_id"), F.col("src").alias("node"), "ts_us"), 3)
    return found.select("*", r(A.time_encoding(F.col("age_us"), 2)[0]).alias("code"))


_U = f"({sql_hash32(chr(99) + 'oncat(' + chr(39) + '4:' + chr(39) + ', start, ' + chr(39) + ':' + chr(39) + ', rep, ' + chr(39) + ':' + chr(39) + ', pos + 1, ' + chr(39) + ':' + chr(39) + ', dst)')} + 1) / 4294967297.0"


@query(
    f"""WITH RECURSIVE e AS ({q.EVENT_EDGES}), w(start, rep, pos, node) AS (SELECT src, rep, 0, src FROM (SELECT DISTINCT src FROM e), range(2) AS r(rep)
    UNION ALL SELECT start, rep, any_value(pos) + 1, arg_min(dst, (-ln({_U}) / w, dst)) FROM (SELECT w.start, w.rep, w.pos, e.dst, e.w FROM w JOIN e ON e.src = w.node WHERE w.pos < 4) GROUP BY start, rep)
    SELECT start, CAST(rep AS INTEGER) AS rep, CAST(pos AS INTEGER) AS pos, node FROM w"""
)
def bl_walks_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    return A.walks(e, G.nodes_of(e), 4, 2, 4)


@query()
def bl_biased_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    return A.walks(e, G.nodes_of(e), 3, 1, 4, p=0.5, q=2.0)


_T = sql_hash32("concat('6:', start, ':', pos + 1, ':', dst, ':', ts_us)")


@query(
    f"""WITH RECURSIVE e AS (SELECT src, dst, ts_us FROM ({q.EVENTS}) UNION ALL SELECT dst, src, ts_us FROM ({q.EVENTS})), w(start, pos, node, t_at) AS (SELECT DISTINCT src, 0, src, -1::BIGINT FROM e
    UNION ALL SELECT start, any_value(pos) + 1, arg_min(dst, ({_T}, dst, ts_us)), arg_min(ts_us, ({_T}, dst, ts_us)) FROM (SELECT w.start, w.pos, e.dst, e.ts_us FROM w JOIN e ON e.src = w.node AND e.ts_us > w.t_at WHERE w.pos < 3) GROUP BY start)
    SELECT start, CAST(pos AS INTEGER) AS pos, node, t_at AS ts_us FROM w"""
)
def bl_temporal_walks_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = T.interactions(spark, sf_dir).select("src", "dst", "ts_us")
    both = G.mirrored(e)
    return A.temporal_walks(both, G.nodes_of(both), 3, 6)


@query()
def bl_walk_embedding(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    return A.walk_embedding(A.walks(e, G.nodes_of(e), 4, 2, 4), 8, ["start", "rep"]).select("node", F.size("z").alias("dims"))


@query(f"SELECT node, CAST(rank AS INTEGER) AS rank, {sql_r('value')} AS value FROM (SELECT node, value, row_number() OVER (PARTITION BY node ORDER BY ts_us DESC, seq DESC) AS rank FROM (SELECT src AS node, ts_us, seq, value FROM ({q.EVENTS}) UNION ALL SELECT dst, ts_us, seq, value FROM ({q.EVENTS}))) WHERE rank <= 4")
def bl_mailbox(spark: SparkSession, sf_dir: str) -> DataFrame:
    return A.mailbox(T.interactions(spark, sf_dir), 4).withColumn("value", r("value"))


_PAIR = f"SELECT l_suppkey + {q.S} AS src, min(o_custkey) + {q.C} AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"
_SE = q.edges_of(q.SUPPLIES)
_SS = f"WITH e AS ({_SE}), p AS (SELECT a.src AS src, b.src AS dst FROM (SELECT DISTINCT src FROM e WHERE src >= {q.S}) AS a JOIN (SELECT DISTINCT src FROM e WHERE src >= {q.S}) AS b ON b.src = a.src + 1)"


def _supplier_pairs(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    e = G.weighted(G.mirrored(T.trades(spark, sf_dir, "supplier").select("src", "dst", "w")))
    s = e.filter(F.col("src") >= T.SUPPLIER).select("src").distinct()
    return e, s.join(s.select((F.col("src") - 1).alias("src"), F.col("src").alias("dst")), "src")


@query(f"{_SS} SELECT p.src, p.dst, count(a.dst) AS n FROM p LEFT JOIN (SELECT e.src, f.src AS other, e.dst FROM e JOIN e AS f ON e.dst = f.dst AND f.src = e.src + 1) AS a ON a.src = p.src AND a.other = p.dst GROUP BY 1, 2")
def bl_common_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return A.common_neighbours(*_supplier_pairs(spark, sf_dir))


@query(f"{_SS}, d AS (SELECT src AS node, sum(w) AS d FROM e GROUP BY src) SELECT p.src, p.dst, a.d * b.d AS score FROM p JOIN d AS a ON a.node = p.src JOIN d AS b ON b.node = p.dst")
def bl_pref_attachment(spark: SparkSession, sf_dir: str) -> DataFrame:
    return A.preferential_attachment(*_supplier_pairs(spark, sf_dir))


@query(f"SELECT seq, count(*) OVER (PARTITION BY src, dst ORDER BY ts_us, seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM ({q.EVENTS})")
def bl_recurrence(spark: SparkSession, sf_dir: str) -> DataFrame:
    return A.recurrence(T.interactions(spark, sf_dir))


def _by_step(f, spark: SparkSession, sf_dir: str, events: bool = False) -> DataFrame:
    deltas = daily(spark, sf_dir)
    rows = T.interactions(spark, sf_dir).select("seq", "ts_us", "src", "dst", G.bucket().alias("step")) if events else deltas
    return N.in_one_task(f, rows, random_x(deltas, 4)).select("step", "node", F.size("z").alias("dims"), r(F.aggregate("z", F.lit(0.0), lambda a, x: a + x), 4).alias("total"))


@query(
    f"""WITH RECURSIVE dl AS ({q.stepped()}), st AS (SELECT DISTINCT step FROM dl), e AS (SELECT st.step, src, dst, sum(dw) AS w FROM st JOIN dl ON dl.step <= st.step GROUP BY ALL), g AS (SELECT step, src AS node, sum(w) AS d FROM e GROUP BY 1, 2)
    SELECT step, node, {sql_r('avg(d) OVER (PARTITION BY node ORDER BY step)')} AS z FROM g"""
)
def bl_moving_average(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running mean over steps of each node's degree at the step, as the simplest layer."""
    deltas = daily(spark, sf_dir)
    steps = [x["step"] for x in deltas.select("step").distinct().collect()]
    d = G.snapshots(deltas, steps).groupBy("step", F.col("src").alias("node")).agg(F.sum("w").alias("d"))
    return A.moving_average(d.select("step", "node", F.array("d").alias("z")), 1).select("step", "node", r(F.col("z")[0]).alias("z"))


def _neural(name: str, f, events: bool = False) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _by_step(f, spark, sf_dir, events)

    run.__name__ = name
    query()(run)


_neural("bl_mutual_memory", N.memory("mutual", 8), True)
_neural("bl_event_memory", N.memory("event", 8), True)
_neural("bl_memory_attention", N.memory("attend", 8), True)
_neural("bl_evolving_conv_h", N.evolving_conv("H", 8))
_neural("bl_evolving_conv_o", N.evolving_conv("O", 8))
_neural("bl_state_update_average", N.state_update_conv("average", 8))
_neural("bl_state_update_dense", N.state_update_conv("dense", 8))
_neural("bl_state_update_gru", N.state_update_conv("gru", 8))
_neural("bl_warm_autoencoder", N.autoencoder("warm", 8))
_neural("bl_lookback_autoencoder", N.autoencoder("lookback", 8))
_neural("bl_variational_autoencoder", N.autoencoder("variational", 8))
_neural("bl_snapshot_attention", N.snapshot_attention(8))
