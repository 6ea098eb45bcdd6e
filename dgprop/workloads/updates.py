"""Incremental repair, timelines, sequences, splits and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.functions.hashing import sql_hash32
from dgprop.operators import graph as G
from dgprop.operators import metrics as M
from dgprop.operators import propagate as pr
from dgprop.operators import sequences as S
from dgprop.operators import timeline as TL
from dgprop.operators.filters import FilterSpec
from dgprop.operators.update import drop_nodes, repair, repair_pull
from dgprop.plans.lineage import cut
from dgprop.sources import tables as T
from dgprop.tasks import splits
from dgprop.workloads import sqltext as q
from dgprop.workloads.graphs import ALTERNATING, RESTART, RETURNS, TTL, daily, event_edges, random_x
from dgprop.workloads.registry import long_form, query, r, sql_r

# Repair: the state of the first half of the events, changed, pushed on; checked against the series on the new graph.
LOOSER, TIGHT, ROUNDS, SPLIT = 1e-11, 1e-13, 48, 5
_EV = q.EVENTS
_OLD = q.edges_of(f"SELECT * FROM ({_EV}) WHERE seq % {SPLIT} <> 0")
_ALL_NODES = f"SELECT src AS node FROM ({_EV}) UNION SELECT dst FROM ({_EV})"


def _halves(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Edges of most events, the other events' deltas, and features of all nodes."""
    e = T.interactions(spark, sf_dir)
    old = G.weighted(G.mirrored(e.filter(F.col("seq") % SPLIT != 0).select("src", "dst", "w")))
    new = G.mirrored(e.filter(F.col("seq") % SPLIT == 0).select("src", "dst", "w")).groupBy("src", "dst").agg(F.sum("w").alias("dw"))
    return cut(old), cut(new), cut(random_x(e, 2))


def _pushed(edges: DataFrame, x: DataFrame, spec: FilterSpec = RESTART) -> DataFrame:
    return pr.push(edges, pr.init_state(x, edges, [spec], 2), [spec], LOOSER, 2).state


def _repaired(old: DataFrame, deltas: DataFrame, x: DataFrame, new_x: DataFrame | None = None, spec: FilterSpec = RESTART) -> DataFrame:
    state = repair(_pushed(old, x, spec), deltas, old, x, [spec], 2, new_x)
    return pr.push(cut(G.apply_deltas(old, deltas)), state, [spec], LOOSER, 2).readout()


def _series(edges: str, x: str | None = None, nodes: str = _ALL_NODES, g0: float = 0.5, ratio: float = 0.5) -> str:
    select = f"SELECT node, dim, {sql_r(f'sum(v * ({q.geometric(g0, ratio)}))', 5)} AS z FROM t GROUP BY node, dim"
    return q.series(edges, 2, "", 0.5, 0.5, ROUNDS, nodes, x, select)


@query(_series(q.EVENT_EDGES))
def up_insert_only(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long_form(_repaired(*_halves(spark, sf_dir)), "node", places=5)


@query(_series(_OLD))
def up_delete_only(spark: SparkSession, sf_dir: str) -> DataFrame:
    old, new, x = _halves(spark, sf_dir)
    gone = new.withColumn("dw", -F.col("dw"))
    return long_form(_repaired(cut(G.apply_deltas(old, new)), gone, x), "node", places=5)


_MIXED = q.edges_of(f"SELECT src, dst, CASE WHEN seq % {SPLIT} = 1 THEN 0.5 ELSE w END AS w FROM ({_EV}) WHERE seq % {SPLIT} <> 2")


@query(_series(_MIXED, g0=0.5, ratio=-0.5))
def up_mixed_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Adds, deletes and halved weights in one batch, for the alternating filter."""
    e = T.interactions(spark, sf_dir)
    old, new, x = _halves(spark, sf_dir)
    part = F.col("seq") % SPLIT
    changes = e.withColumn("dw", F.when(part == 0, 1.0).when(part == 1, -0.5).when(part == 2, -1.0)).filter("dw IS NOT NULL").select("src", "dst", "dw")
    deltas = cut(G.mirrored(changes).groupBy("src", "dst").agg(F.sum("dw").alias("dw")).filter(F.abs("dw") > 1e-12))
    return long_form(_repaired(old, deltas, x, spec=ALTERNATING), "node", places=5)


_ISOLATED = f"SELECT * FROM ({_EV}) WHERE src % 7 <> 0"


@query(_series(q.edges_of(_ISOLATED)))
def up_zero_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every seventh user loses all edges."""
    x = cut(random_x(T.interactions(spark, sf_dir), 2))
    edges = cut(event_edges(spark, sf_dir))
    gone = edges.filter((F.col("src") < T.ITEM) & (F.col("src") % 7 == 0)).select(F.col("src").alias("node")).distinct()
    return long_form(_repaired(edges, cut(G.delete_node_deltas(edges, gone)), x), "node", places=5)


@query(_series(q.EVENT_EDGES, x=q.features("SELECT node FROM n WHERE node % 3 <> 0", 2) + " UNION ALL " + q.features("SELECT node FROM n WHERE node % 3 = 0", 2, 9)))
def up_feature_change(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges = cut(event_edges(spark, sf_dir))
    x = cut(random_x(edges, 2))
    new_x = cut(T.random_features(x.filter("node % 3 = 0"), 2, 9))
    empty = edges.limit(0).select("src", "dst", F.col("w").alias("dw"))
    return long_form(_repaired(edges, empty, x, new_x), "node", places=5)


@query(_series(q.EVENT_EDGES))
def up_node_add(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every fifth user and its edges come in later."""
    edges = cut(event_edges(spark, sf_dir))
    late = (F.col("src") < T.ITEM) & (F.col("src") % 5 == 0) | (F.col("dst") < T.ITEM) & (F.col("dst") % 5 == 0)
    x = cut(random_x(edges, 2))
    old_x = cut(x.filter(~((F.col("node") < T.ITEM) & (F.col("node") % 5 == 0))))
    new_x = cut(x.join(old_x, "node", "left_anti"))
    return long_form(_repaired(cut(edges.filter(~late)), cut(edges.filter(late).withColumnRenamed("w", "dw")), old_x, new_x), "node", places=5)


@query(_series(q.edges_of(_ISOLATED), nodes=f"SELECT src AS node FROM ({_ISOLATED}) UNION SELECT dst FROM ({_EV})"))
def up_node_delete(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = cut(random_x(T.interactions(spark, sf_dir), 2))
    edges = cut(event_edges(spark, sf_dir))
    gone = edges.filter((F.col("src") < T.ITEM) & (F.col("src") % 7 == 0)).select(F.col("src").alias("node")).distinct()
    return long_form(drop_nodes(_repaired(edges, cut(G.delete_node_deltas(edges, gone)), x), gone), "node", places=5)


@query("SELECT 1 AS same, 1 AS keeps_identity")
def up_pull_equals_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    old, new, x = _halves(spark, sf_dir)
    state = _pushed(old, x)
    after = cut(G.apply_deltas(old, new))
    one = cut(repair(state, new, old, x, [RESTART], 2))
    two = repair_pull(state, after, G.affected(new), x, [RESTART], 2)
    gap = one.join(two.select("node", F.col("q0_0").alias("a"), F.col("q0_1").alias("b")), "node").agg(F.max(F.greatest(F.abs(F.col("q0_0") - F.col("a")), F.abs(F.col("q0_1") - F.col("b")))).alias("gap"))
    held = pr.identity_gap(one, after, x, RESTART, 2).withColumnRenamed("gap", "held")
    return gap.join(held).select((F.col("gap") < 1e-10).cast("int").alias("same"), (F.col("held") < 1e-10).cast("int").alias("keeps_identity"))


# Timelines


def _steps_z(result: TL.TimelineResult) -> DataFrame:
    return long_form(result.representations, "step", "node", places=5)


@query(q.series_by_step(q.stepped(), 2, 0.5, 0.5, 0.5, ROUNDS))
def tl_daily_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    deltas = daily(spark, sf_dir)
    return _steps_z(TL.run_timeline(deltas, random_x(deltas, 2), [RESTART], TIGHT, 2))


_TTL_DELTAS = q.stepped(rows=TTL, dw="CASE WHEN kind = 'add_edge' THEN w ELSE -w END")


@query(q.series_by_step(_TTL_DELTAS, 1, 0.5, -0.5, 0.5, ROUNDS))
def tl_sliding_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every edge goes a week after it came."""
    deltas = G.net_deltas(T.with_expiry(T.interactions(spark, sf_dir), 7).withColumn("step", G.bucket()))
    return _steps_z(TL.run_timeline(deltas, random_x(deltas, 1), [ALTERNATING], TIGHT, 1))


_YEAR = "year(make_timestamp(ts_us))"
_YEARLY = q.stepped(_YEAR, q.SUPPLIES)


@query(q.series_by_step(_YEARLY, 1, 0.5, 0.5, 0.5, ROUNDS))
def tl_yearly_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = T.trades(spark, sf_dir, "supplier").withColumn("step", F.year(F.timestamp_micros("ts_us")))
    deltas = G.net_deltas(rows)
    return _steps_z(TL.run_timeline(deltas, random_x(deltas, 1), [RESTART], TIGHT, 1))


@query(f"SELECT node, dim, {sql_r('z', 5)} AS z FROM ({_series(q.EVENT_EDGES)})")
def tl_ctdg_vs_dtdg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Small steps of 100 events end where one batch of all of them does."""
    deltas = G.net_deltas(G.by_count(T.interactions(spark, sf_dir), 100))
    done = TL.run_timeline(deltas, random_x(deltas, 2), [RESTART], TIGHT, 2, emit="last")
    return long_form(done.representations, "node", places=5)


@query(q.series_by_step(q.stepped(), 2, 0.5, 0.5, 0.5, ROUNDS))
def bl_recompute(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every step from a cold start."""
    deltas = daily(spark, sf_dir)
    return _steps_z(TL.run_timeline(deltas, random_x(deltas, 2), [RESTART], TIGHT, 2, strategy="recompute"))


@query(q.series_by_step(q.stepped(), 2, 0.5, 0.5, 0.5, ROUNDS))
def tl_auto_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    deltas = daily(spark, sf_dir)
    return _steps_z(TL.run_timeline(deltas, random_x(deltas, 2), [RESTART], TIGHT, 2, strategy="auto"))


@query(q.series(q.EVENT_EDGES, 172, "", 0.5, 0.5, ROUNDS, _ALL_NODES, None, f"SELECT node, dim, {sql_r(f'sum(v * ({q.geometric(0.5, 0.5)}))', 5)} AS z FROM t GROUP BY node, dim"))
def tl_wide_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The width of the published features, 172 columns, over daily steps; the last step's rows."""
    deltas = daily(spark, sf_dir)
    done = TL.run_timeline(deltas, random_x(deltas, 172), [RESTART], TIGHT, 172, emit="last")
    return long_form(done.representations, "node", places=5)


@query("SELECT 1 AS within, 1 AS touches_less")
def tl_recompute_equals_incremental(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both are within the bound of each other; small daily changes cost less to repair than to start anew."""
    deltas = G.net_deltas(T.interactions(spark, sf_dir).withColumn("step", G.bucket(T.DAY_US // 24)))
    x, rmax = random_x(deltas, 1), 1e-3
    one = TL.run_timeline(deltas, x, [RESTART], rmax, 1)
    two = TL.run_timeline(deltas, x, [RESTART], rmax, 1, strategy="recompute")
    gap = one.representations.join(two.representations.withColumnRenamed("z", "o"), ["step", "node"]).agg(F.max(F.abs(F.col("z")[0] - F.col("o")[0])).alias("gap"))
    d = G.degrees(G.graph_at(deltas, 1 << 30)).agg(F.max("d").alias("d"))
    cost = one.stats.agg(F.sum("edges_touched").alias("a")).join(two.stats.agg(F.sum("edges_touched").alias("b")))
    return gap.join(d).join(cost).select((F.col("gap") <= 2 * rmax * RESTART.mass * F.sqrt("d")).cast("int").alias("within"), (F.col("a") < F.col("b")).cast("int").alias("touches_less"))


@query()
def tl_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of every strategy over the daily steps."""
    deltas = daily(spark, sf_dir)
    x, out = random_x(deltas, 1), None
    for strategy in ("incremental", "recompute", "auto"):
        stats = TL.run_timeline(deltas, x, [RESTART], 1e-3, 1, strategy=strategy).stats.withColumn("strategy", F.lit(strategy))
        out = stats if out is None else out.unionByName(stats)
    return out.drop("potential", "max_abs_q")


# Sequences


def _daily_z(spark: SparkSession, sf_dir: str) -> DataFrame:
    deltas = daily(spark, sf_dir)
    return TL.run_timeline(deltas, random_x(deltas, 2), [RESTART], TIGHT, 2).representations


_DAILY_Z = q.series_by_step(q.stepped(), 2, 0.5, 0.5, 0.5, ROUNDS, select="SELECT step, node, list(v ORDER BY dim) AS z FROM (SELECT step, node, dim, sum(v * (0.5 * pow(0.5, k))) AS v FROM t GROUP BY step, node, dim) GROUP BY step, node")
_PAST = f"SELECT step, node, z, lag(z) OVER (PARTITION BY node ORDER BY step) AS old FROM ({_DAILY_Z})"


@query(f"SELECT step, node, {sql_r('z[1] - old[1]', 5)} AS d0, {sql_r('z[2] - old[2]', 5)} AS d1 FROM ({_PAST}) WHERE old IS NOT NULL")
def sq_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.deltas(_daily_z(spark, sf_dir)).select("step", "node", r(F.col("delta")[0], 5).alias("d0"), r(F.col("delta")[1], 5).alias("d1"))


@query(f"SELECT step, node, {sql_r('sqrt(pow(z[1] - old[1], 2) + pow(z[2] - old[2], 2))', 5)} AS d FROM ({_PAST}) WHERE old IS NOT NULL")
def sq_l2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.deltas(_daily_z(spark, sf_dir), "l2").select("step", "node", r(F.col("delta")[0], 5).alias("d"))


@query(f"SELECT step, node, {sql_r('1 - list_dot_product(z, old) / (sqrt(list_dot_product(z, z)) * sqrt(list_dot_product(old, old)))', 4)} AS d FROM ({_PAST}) WHERE old IS NOT NULL")
def sq_cosine(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.deltas(_daily_z(spark, sf_dir), "cosine").select("step", "node", r(F.col("delta")[0], 4).alias("d"))


@query(f"WITH c AS (SELECT step, node, z[1] - old[1] AS d FROM ({_PAST}) WHERE old IS NOT NULL) SELECT step, node, count(*) OVER w AS n, {sql_r('sum(d) OVER w', 5)} AS total FROM c WINDOW w AS (PARTITION BY node ORDER BY step ROWS BETWEEN 4 PRECEDING AND CURRENT ROW)")
def sq_window_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = S.sequences(S.deltas(_daily_z(spark, sf_dir)), 5)
    return s.select("step", "node", F.size("deltas").cast("bigint").alias("n"), r(F.aggregate("deltas", F.lit(0.0), lambda a, d: a + d[0]), 5).alias("total"))


@query(f"WITH c AS (SELECT step, node, unnest([0, 1]) AS dim, unnest([z[1] - old[1], z[2] - old[2]]) AS d FROM ({_PAST}) WHERE old IS NOT NULL) SELECT step, CAST(dim AS INTEGER) AS dim, CAST(row_number() OVER w AS INTEGER) AS rank, {sql_r('abs(d)', 5)} AS score FROM c WINDOW w AS (PARTITION BY step, dim ORDER BY round(abs(d), 9) DESC, node) QUALIFY row_number() OVER w <= 3")
def sq_influence_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.influence(S.deltas(_daily_z(spark, sf_dir)), 3).select("step", "dim", "rank", r("score", 5).alias("score"))


# Tasks

_PAIRS = f"SELECT seq AS query_id, CAST(ts_us // {q.DAY} AS INTEGER) AS step, src, dst FROM ({q.EVENTS})"
_TRADE_PAIRS = f"SELECT seq AS query_id, CAST(ts_us // {q.DAY} AS INTEGER) AS step, src, dst FROM ({q.TRADES})"


def _split_sql(pairs: str) -> str:
    return f"""SELECT p.*, CASE WHEN before * 100 < total * 70 THEN 'train' WHEN before * 100 < total * 85 THEN 'valid' ELSE 'test' END AS part FROM ({pairs}) AS p
        JOIN (SELECT step, coalesce(sum(n) OVER (ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before, sum(n) OVER () AS total FROM (SELECT step, count(*) AS n FROM ({pairs}) GROUP BY step)) USING (step)"""


def event_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.interactions(spark, sf_dir).select(F.col("seq").alias("query_id"), G.bucket().alias("step"), "src", "dst")


def trade_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.trades(spark, sf_dir).select(F.col("seq").alias("query_id"), G.bucket().alias("step"), "src", "dst")


@query(_split_sql(_PAIRS))
def tk_time_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return splits.time_split(event_pairs(spark, sf_dir))


_SEEN = "src IN (SELECT src FROM s WHERE part = 'train') AND dst IN (SELECT dst FROM s WHERE part = 'train')"


@query(f"WITH s AS ({_split_sql(_TRADE_PAIRS)}) SELECT * FROM s WHERE part = 'test' AND {_SEEN}")
def tk_transductive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return splits.in_setting(splits.time_split(trade_pairs(spark, sf_dir)), "transductive")


@query(f"WITH s AS ({_split_sql(_TRADE_PAIRS)}) SELECT * FROM s WHERE part = 'test' AND NOT ({_SEEN})")
def tk_inductive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return splits.in_setting(splits.time_split(trade_pairs(spark, sf_dir)), "inductive")


_HOLD = sql_hash32("concat('5:', node)")


@query(f"SELECT node FROM ({_ALL_NODES}) WHERE {_HOLD} % 100 < 10")
def tk_holdout_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return splits.holdout_nodes(G.nodes_of(T.interactions(spark, sf_dir)), 10, 5)


def _negatives_sql(k: int, pairs: str) -> str:
    draw = sql_hash32("concat('3:', query_id, ':', j)")
    return f"""WITH p AS ({pairs}), e AS ({q.EVENTS}), pool AS (SELECT row_number() OVER (ORDER BY node) - 1 AS idx, node FROM (SELECT DISTINCT dst AS node FROM e)),
        free AS (SELECT s.src, pool.node, row_number() OVER (PARTITION BY s.src ORDER BY idx) - 1 AS place, count(*) OVER (PARTITION BY s.src) AS n_free FROM (SELECT DISTINCT src FROM e) AS s, pool WHERE NOT EXISTS (SELECT 1 FROM e WHERE e.src = s.src AND e.dst = pool.node)),
        d AS (SELECT p.query_id, p.step, p.src, n_free, j, CASE WHEN n_free <= {k} THEN j - 1 ELSE {draw} % n_free END AS place FROM p JOIN (SELECT DISTINCT src, n_free FROM free) USING (src), range(1, {k + 1}) AS a(j) WHERE j <= n_free)
        SELECT query_id, step, d.src, node AS dst, 0 AS label, CAST(j AS INTEGER) AS j, d.n_free FROM d JOIN free ON free.src = d.src AND free.place = d.place"""


def _negatives(spark: SparkSession, sf_dir: str, k: int, pairs: DataFrame) -> DataFrame:
    e = T.interactions(spark, sf_dir)
    pool = splits.indexed(e.select(F.col("dst").alias("node")).distinct())
    return splits.negatives(pairs, pool, k, 3, e)


@query(_negatives_sql(1, _PAIRS))
def tk_negatives_1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _negatives(spark, sf_dir, 1, event_pairs(spark, sf_dir))


@query(_negatives_sql(1000, f"SELECT * FROM ({_split_sql(_PAIRS)}) WHERE part = 'test'"))
def tk_negatives_ranked(spark: SparkSession, sf_dir: str) -> DataFrame:
    """1000 for each pair of the test part, or all that there are."""
    return _negatives(spark, sf_dir, 1000, splits.time_split(event_pairs(spark, sf_dir)).filter("part = 'test'"))


@query(f"WITH z AS ({_DAILY_Z}), p AS (SELECT query_id, src AS node, step - 1 AS step FROM ({_PAIRS})) SELECT query_id, p.node, p.step, z.step AS as_of, {sql_r('z.z[1]', 5)} AS z0 FROM p ASOF JOIN z ON p.node = z.node AND p.step >= z.step")
def tk_asof_latest(spark: SparkSession, sf_dir: str) -> DataFrame:
    queries = event_pairs(spark, sf_dir).select("query_id", F.col("src").alias("node"), (F.col("step") - 1).alias("step"))
    return S.as_of(_daily_z(spark, sf_dir), queries).select("query_id", "node", "step", "as_of", r(F.col("z")[0], 5).alias("z0"))


# Measures, on scores that a hash gives and on counts

_SCORED = f"SELECT query_id, step, src, {sql_hash32(chr(39) + 's:' + chr(39) + ' || query_id')} % 50 / 10.0 AS score, CASE WHEN value > 50 THEN 1 ELSE 0 END AS label FROM (SELECT seq AS query_id, CAST(ts_us // {q.DAY} AS INTEGER) AS step, src, value FROM ({q.EVENTS}))"


def _scored(spark: SparkSession, sf_dir: str) -> DataFrame:
    from dgprop.functions.hashing import hash32

    e = T.interactions(spark, sf_dir)
    return e.select(F.col("seq").alias("query_id"), G.bucket().alias("step"), "src", (F.pmod(hash32("s", F.col("seq")), F.lit(50)) / 10.0).alias("score"), F.when(F.col("value") > 50, 1).otherwise(0).alias("label"))


@query(f"WITH g AS (SELECT step, score, sum(label)::DOUBLE AS pos, count(*)::DOUBLE AS n FROM ({_SCORED}) GROUP BY 1, 2), c AS (SELECT *, sum(pos) OVER w AS tp, sum(n) OVER w AS seen FROM g WINDOW w AS (PARTITION BY step ORDER BY score DESC)) SELECT step, {sql_r('sum(pos * tp / seen) / nullif(sum(pos), 0)')} AS average_precision FROM c GROUP BY step")
def mt_average_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    return M.average_precision(_scored(spark, sf_dir), ["step"]).withColumn("average_precision", r("average_precision"))


@query(f"WITH s AS ({_SCORED}), k AS (SELECT label, rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2.0 AS mid FROM s) SELECT {sql_r('(sum(mid) FILTER (label = 1) - count(*) FILTER (label = 1) * (count(*) FILTER (label = 1) + 1) / 2.0) / (count(*) FILTER (label = 1) * count(*) FILTER (label = 0)::DOUBLE)')} AS roc_auc FROM k")
def mt_roc_auc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return M.roc_auc(_scored(spark, sf_dir)).withColumn("roc_auc", r("roc_auc"))


_RANKED = f"SELECT src AS query_id, step, score, CASE WHEN query_id = min(query_id) OVER (PARTITION BY src, step) THEN 1 ELSE 0 END AS label FROM ({_SCORED})"


@query(f"WITH s AS ({_RANKED}), p AS (SELECT query_id, step, score AS own FROM s WHERE label = 1), c AS (SELECT p.query_id, p.step, count(*) FILTER (s.label = 0 AND s.score > own) AS above, count(*) FILTER (s.label = 0 AND s.score = own) AS level FROM p JOIN s ON p.query_id = s.query_id AND p.step = s.step GROUP BY 1, 2 HAVING count(*) > 0) SELECT {sql_r('avg(m)')} AS mrr FROM (SELECT step, avg(1 / (1 + above + 0.5 * level)) AS m FROM c GROUP BY step)")
def mt_mrr(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import Window

    first = F.min("query_id").over(Window.partitionBy("src", "step"))
    rows = _scored(spark, sf_dir).withColumn("label", (F.col("query_id") == first).cast("int")).select(F.col("src").alias("query_id"), "step", "score", "label")
    return M.mrr(rows).withColumn("mrr", r("mrr"))


_CLASSES = f"SELECT label, CAST(floor(score) AS INTEGER) % 2 AS predicted FROM ({_SCORED})"


@query(f"WITH s AS ({_CLASSES}), c AS (SELECT k, count(*) FILTER (label = k AND predicted = k)::DOUBLE AS tp, count(*) FILTER (label = k) AS t, count(*) FILTER (predicted = k) AS p FROM s, range(2) AS r(k) GROUP BY k) SELECT {sql_r('2 * sum(tp) / (sum(t) + sum(p))')} AS f1_micro, {sql_r('avg(2 * tp / (t + p))')} AS f1_macro FROM c")
def mt_f1_micro(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _scored(spark, sf_dir).select("label", (F.floor("score").cast("int") % 2).alias("predicted"))
    return M.f1(rows).select(r("f1_micro").alias("f1_micro"), r("f1_macro").alias("f1_macro"))


@query(f"SELECT label, {sql_r('avg(score)')} AS mean, {sql_r('stddev_samp(score)')} AS std, count(*) AS n_seeds FROM ({_SCORED}) GROUP BY label")
def mt_seed_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return M.summarise_seeds(_scored(spark, sf_dir), ["label"], "score").withColumns({"mean": r("mean"), "std": r("std")})


@query(f"SELECT {sql_r('avg(CASE WHEN k > 1 THEN 1.0 ELSE 0.0 END)')} AS conflict_rate FROM (SELECT src, count(DISTINCT event_type) AS k FROM ({q.EVENTS}) GROUP BY src)")
def mt_label_conflicts(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = T.interactions(spark, sf_dir).select(F.col("src").alias("node"), F.col("event_type").alias("label"))
    return M.label_conflict_rate(rows).withColumn("conflict_rate", r("conflict_rate"))
