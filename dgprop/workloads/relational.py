"""The relational surface that the methods stand on, one query for each form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dgprop.functions import vectors as V
from dgprop.functions.udfs import half_edges, squash, vec_sum_agg
from dgprop.operators import graph as G
from dgprop.plans.skew import salted_join
from dgprop.sources import tables as T
from dgprop.workloads import sqltext as q
from dgprop.workloads.registry import query, r, sql_r


def _t(name: str):
    return lambda spark, sf_dir: T.table(spark, sf_dir, name)


EV, LI, OR, CU, NA = (_t(n) for n in ("events", "lineitem", "orders", "customer", "nation"))


@query("SELECT event_id, user_id, value FROM events WHERE value > 50")
def op_scan_project(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).filter("value > 50").select("event_id", "user_id", "value")


@query("SELECT event_id, event_type FROM events WHERE event_type IN ('view', 'click') AND user_id BETWEEN 10 AND 40")
def op_filter_kinds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).filter(F.col("event_type").isin("view", "click") & F.col("user_id").between(10, 40)).select("event_id", "event_type")


@query("SELECT event_id, CASE WHEN value > 80 THEN 'high' WHEN value > 20 THEN 'mid' ELSE 'low' END AS band FROM events")
def op_case_when(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).select("event_id", F.when(F.col("value") > 80, "high").when(F.col("value") > 20, "mid").otherwise("low").alias("band"))


@query(f"SELECT event_id, coalesce(nullif(event_type, 'view'), 'none') AS kind, {sql_r('value / nullif(user_id % 3, 0)')} AS ratio FROM events")
def op_null_handling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).select("event_id", F.coalesce(F.nullif("event_type", F.lit("view")), F.lit("none")).alias("kind"), r(F.try_divide(F.col("value"), F.col("user_id") % 3)).alias("ratio"))


_JOIN = "SELECT o_custkey, count(*) AS n, " + sql_r("sum(l_quantity)", 2) + " AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey"


def _joined(spark: SparkSession, sf_dir: str, hint: str) -> DataFrame:
    o, li = OR(spark, sf_dir).hint(hint), LI(spark, sf_dir)
    return o.join(li, o.o_orderkey == li.l_orderkey).groupBy("o_custkey").agg(F.count("*").alias("n"), r(F.sum("l_quantity"), 2).alias("quantity"))


@query(_JOIN)
def op_join_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _joined(spark, sf_dir, "shuffle_hash")


@query(_JOIN)
def op_join_sort_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _joined(spark, sf_dir, "merge")


@query("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def op_join_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n = CU(spark, sf_dir), NA(spark, sf_dir)  # 25 nations, whatever the scale
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).select("c_custkey", "n_name")


@query(f"WITH e AS ({q.EVENTS}) SELECT o_custkey AS k, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def op_join_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = LI(spark, sf_dir).select(F.col("l_orderkey").alias("k0"), "l_linenumber")
    o = OR(spark, sf_dir).select(F.col("o_orderkey").alias("k0"), "o_custkey")
    return salted_join(li, o, "k0", 5, 4).groupBy(F.col("o_custkey").alias("k")).agg(F.count("*").alias("n"))


@query("SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier AS a JOIN supplier AS b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal")
def op_join_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = T.table(spark, sf_dir, "supplier")
    a, b = s.alias("a"), s.alias("b")
    return a.join(b, (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_acctbal") < F.col("b.s_acctbal"))).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@query(f"WITH e AS ({q.EVENTS}), d AS (SELECT unnest(range(19724, 19754)) AS day) SELECT day, count(*) AS alive FROM d JOIN e ON ts_us // {q.DAY} <= day AND day < ts_us // {q.DAY} + 7 GROUP BY day")
def op_join_range_ttl(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events alive on each day for a week: a range join as an equi-join on the days of each event."""
    e = T.interactions(spark, sf_dir).select(F.floor(F.col("ts_us") / T.DAY_US).alias("d"))
    alive = e.select(F.explode(F.sequence(F.col("d"), F.col("d") + 6)).alias("day"))
    return alive.filter("day BETWEEN 19724 AND 19753").groupBy("day").agg(F.count("*").alias("alive"))


_HOUR = 3_600_000_000


@query(f"WITH e AS ({q.EVENTS}) SELECT a.seq AS seq, count(b.seq) AS later FROM e AS a JOIN e AS b ON a.src = b.src AND b.ts_us > a.ts_us AND b.ts_us <= a.ts_us + {6 * _HOUR} GROUP BY a.seq")
def op_join_interval_walk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps that a walk in time can take next: same user, within six hours, joined by buckets of that width."""
    e, width = T.interactions(spark, sf_dir), 6 * _HOUR
    a = e.select("seq", "src", F.col("ts_us").alias("t"), F.explode(F.array(F.floor(F.col("ts_us") / width), F.floor(F.col("ts_us") / width) + 1)).alias("b"))
    b = e.select("src", F.col("ts_us").alias("u"), F.floor(F.col("ts_us") / width).alias("b"))
    return a.join(b, ["src", "b"]).filter(f"u > t AND u <= t + {width}").groupBy("seq").agg(F.count("*").alias("later"))


@query(f"WITH e AS ({q.EVENTS}), c AS (SELECT src, ts_us, value FROM e WHERE event_type = 'click') SELECT e.seq, c.value FROM e ASOF JOIN c ON e.src = c.src AND e.ts_us > c.ts_us WHERE e.event_type = 'purchase'")
def op_join_asof_repr(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A purchase with the user's latest click before it, by one window over both."""
    e = T.interactions(spark, sf_dir).filter("event_type IN ('click', 'purchase')")
    click = F.when(F.col("event_type") == "click", F.col("value"))
    past = Window.partitionBy("src").orderBy("ts_us").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("last", F.last(click, ignorenulls=True).over(past)).filter("event_type = 'purchase' AND last IS NOT NULL").select("seq", F.col("last").alias("value"))


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
def op_join_semi_transductive(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = CU(spark, sf_dir), OR(spark, sf_dir).filter("o_orderstatus = 'F'")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 100000)")
def op_join_anti_inductive(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = CU(spark, sf_dir), OR(spark, sf_dir).filter("o_totalprice > 100000")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_custkey")


@query("SELECT o_orderkey FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey WHERE l_orderkey IS NULL")
def op_join_left_orphans(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, li = OR(spark, sf_dir), LI(spark, sf_dir)
    return o.join(li, o.o_orderkey == li.l_orderkey, "left").filter("l_orderkey IS NULL").select("o_orderkey")


_A = "SELECT l_suppkey AS k, count(*) AS a FROM lineitem WHERE l_returnflag = 'R' AND l_quantity > 45 GROUP BY 1"


@query(f"WITH x AS ({_A}), y AS ({_A.replace('> 45', '< 5').replace('AS a', 'AS b')}) SELECT coalesce(x.k, y.k) AS k, coalesce(a, 0) - coalesce(b, 0) AS d FROM x FULL JOIN y ON x.k = y.k")
def op_join_full_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = LI(spark, sf_dir).filter("l_returnflag = 'R'").withColumn("k", F.col("l_suppkey"))
    a = li.filter("l_quantity > 45").groupBy("k").agg(F.count("*").alias("a"))
    b = li.filter("l_quantity < 5").groupBy("k").agg(F.count("*").alias("b"))
    return a.join(b, "k", "full").select("k", (F.coalesce("a", F.lit(0)) - F.coalesce("b", F.lit(0))).alias("d"))


@query("SELECT r_name, n_name FROM region, nation WHERE r_regionkey <> n_regionkey")
def op_join_cross_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.table(spark, sf_dir, "region").crossJoin(NA(spark, sf_dir)).filter("r_regionkey <> n_regionkey").select("r_name", "n_name")


@query("SELECT a.l_suppkey AS a, b.l_suppkey AS b, count(*) AS n FROM lineitem AS a JOIN lineitem AS b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey GROUP BY 1, 2 HAVING count(*) > 20")
def op_join_self_cosupplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = LI(spark, sf_dir)
    a, b = li.select("l_orderkey", F.col("l_suppkey").alias("a")), li.select("l_orderkey", F.col("l_suppkey").alias("b"))
    return a.join(b, "l_orderkey").filter("a < b").groupBy("a", "b").agg(F.count("*").alias("n")).filter("n > 20")


@query("SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) WHERE c_nationkey = 3")
def op_join_lateral_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = CU(spark, sf_dir).filter("c_nationkey = 3"), OR(spark, sf_dir)
    top = F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return c.join(o, c.c_custkey == o.o_custkey).withColumn("k", top).filter("k <= 2").select("c_custkey", "o_orderkey")


@query(f"SELECT src AS node, sum(w) AS d, count(*) AS n FROM ({q.EVENT_EDGES}) GROUP BY src")
def op_agg_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = G.weighted(G.mirrored(T.interactions(spark, sf_dir).select("src", "dst", "w")))
    return e.groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("d"), F.count("*").alias("n"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def op_agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return LI(spark, sf_dir).groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@query()
def op_agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return LI(spark, sf_dir).groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query(f"SELECT event_type, {sql_r('quantile_cont(value, 0.5)')} AS med, {sql_r('quantile_cont(value, 0.9)')} AS p90 FROM events GROUP BY 1")
def op_agg_percentile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).groupBy("event_type").agg(r(F.percentile("value", 0.5)).alias("med"), r(F.percentile("value", 0.9)).alias("p90"))


@query("SELECT user_id, arg_max(event_id, (value, event_id)) AS top, arg_min(event_id, (value, event_id)) AS low FROM events GROUP BY 1")
def op_agg_maxby(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = F.struct("value", "event_id")
    return EV(spark, sf_dir).groupBy("user_id").agg(F.max_by("event_id", order).alias("top"), F.min_by("event_id", order).alias("low"))


@query("SELECT user_id, string_agg(event_type, ',' ORDER BY event_id) AS kinds FROM events WHERE value > 95 GROUP BY 1")
def op_agg_collect_sorted(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = F.array_sort(F.collect_list(F.struct("event_id", "event_type")))
    return EV(spark, sf_dir).filter("value > 95").groupBy("user_id").agg(rows.alias("x")).select("user_id", F.array_join(F.col("x.event_type"), ",").alias("kinds"))


@query("SELECT user_id, count(*) AS n FROM events GROUP BY 1 HAVING count(*) > 65")
def op_agg_having(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).groupBy("user_id").agg(F.count("*").alias("n")).filter("n > 65")


@query("SELECT user_id % 5 AS g, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'error') AS error FROM events GROUP BY 1")
def op_agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).groupBy((F.col("user_id") % 5).alias("g")).pivot("event_type", ["view", "click", "error"]).count()


def _grouped(kind: str) -> str:
    return f"SELECT CAST(day(ts) AS INTEGER) AS d, event_type, count(*) AS n FROM events GROUP BY {kind}"


def _days(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).select(F.dayofmonth("ts").alias("d"), "event_type")


@query(_grouped("GROUPING SETS ((day(ts)), (event_type), ())"))
def op_agg_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _days(spark, sf_dir).groupingSets([[F.col("d")], [F.col("event_type")], []], F.col("d"), F.col("event_type")).agg(F.count("*").alias("n"))


@query(_grouped("CUBE (day(ts), event_type)"))
def op_agg_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _days(spark, sf_dir).cube("d", "event_type").agg(F.count("*").alias("n"))


@query(_grouped("ROLLUP (day(ts), event_type)"))
def op_agg_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _days(spark, sf_dir).rollup("d", "event_type").agg(F.count("*").alias("n"))


def _window(spark: SparkSession, sf_dir: str, **columns) -> DataFrame:
    return EV(spark, sf_dir).select("event_id", *[c.alias(n) for n, c in columns.items()])


def by(column: str):
    return Window.partitionBy("user_id").orderBy(column)


_PV, _PT = "(PARTITION BY user_id ORDER BY value)", "(PARTITION BY user_id ORDER BY event_id)"


@query(f"SELECT event_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY value, event_id) AS INTEGER) AS rn, CAST(rank() OVER {_PV} AS INTEGER) AS rk, CAST(dense_rank() OVER {_PV} AS INTEGER) AS dr FROM events")
def op_win_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _window(spark, sf_dir, rn=F.row_number().over(Window.partitionBy("user_id").orderBy("value", "event_id")), rk=F.rank().over(by("value")), dr=F.dense_rank().over(by("value")))


@query(f"SELECT event_id, {sql_r(f'percent_rank() OVER {_PV}')} AS pr FROM events")
def op_win_percent_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _window(spark, sf_dir, pr=r(F.percent_rank().over(by("value"))))


@query(f"SELECT event_id, {sql_r(f'value - lag(value) OVER {_PT}')} AS d, {sql_r(f'lead(value) OVER {_PT}')} AS nxt FROM events")
def op_win_lag_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _window(spark, sf_dir, d=r(F.col("value") - F.lag("value").over(by("event_id"))), nxt=r(F.lead("value").over(by("event_id"))))


@query(f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS degree FROM events")
def op_win_running_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _window(spark, sf_dir, degree=F.count("*").over(by("event_id").rowsBetween(Window.unboundedPreceding, 0)))


@query(f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN {7 * q.DAY} PRECEDING AND CURRENT ROW) AS alive FROM events")
def op_win_range_ttl(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = T.interactions(spark, sf_dir)
    return rows.select(F.col("seq").alias("event_id"), F.count("*").over(Window.partitionBy("src").orderBy("ts_us").rangeBetween(-7 * q.DAY, 0)).alias("alive"))


@query(f"SELECT event_id, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS last_click FROM events")
def op_win_last_ignore_nulls(spark: SparkSession, sf_dir: str) -> DataFrame:
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    return _window(spark, sf_dir, last_click=F.last(click, ignorenulls=True).over(by("event_id").rowsBetween(Window.unboundedPreceding, 0)))


@query(f"SELECT event_id, CAST(ntile(4) OVER {_PT} AS INTEGER) AS quarter FROM events")
def op_win_ntile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _window(spark, sf_dir, quarter=F.ntile(4).over(by("event_id")))


@query("SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10")
def op_sort_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return CU(spark, sf_dir).select("c_custkey", "c_acctbal").orderBy(F.desc("c_acctbal"), "c_custkey").limit(10)


@query("SELECT user_id, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) <= 3")
def op_topk_per_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id"))
    return EV(spark, sf_dir).withColumn("k", k).filter("k <= 3").select("user_id", "event_id")


@query("SELECT event_id FROM events ORDER BY value, event_id LIMIT 20 OFFSET 100")
def op_limit_offset(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).orderBy("value", "event_id").offset(100).limit(20).select("event_id")


_S1, _S2 = "SELECT l_partkey AS a, l_suppkey AS b FROM lineitem WHERE l_linenumber = 1", "SELECT l_partkey AS a, l_suppkey AS b FROM lineitem WHERE l_linenumber = 2"


def _pair(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    li = LI(spark, sf_dir)
    return tuple(li.filter(F.col("l_linenumber") == k).select(F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b")) for k in (1, 2))


@query(f"{_S1} UNION {_S2}")
def op_set_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = _pair(spark, sf_dir)
    return x.union(y).distinct()


@query(f"{_S1} INTERSECT {_S2}")
def op_set_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = _pair(spark, sf_dir)
    return x.intersect(y)


@query(f"{_S1} EXCEPT {_S2}")
def op_set_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = _pair(spark, sf_dir)
    return x.subtract(y)


@query(f"{_S1} EXCEPT ALL {_S2}")
def op_set_except_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = _pair(spark, sf_dir)
    return x.exceptAll(y)


@query("SELECT p_partkey, lower(p_name) AS lo, substr(p_brand, 1, 5) AS head, p_type || '-' || p_brand AS joined, levenshtein(p_brand, p_type)::INTEGER AS dist FROM part")
def op_fn_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.table(spark, sf_dir, "part").select("p_partkey", F.lower("p_name").alias("lo"), F.substring("p_brand", 1, 5).alias("head"), F.concat_ws("-", "p_type", "p_brand").alias("joined"), F.levenshtein("p_brand", "p_type").alias("dist"))


@query("SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS INTEGER) AS days FROM orders")
def op_fn_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    return OR(spark, sf_dir).select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).alias("days"))


@query("SELECT event_id, " + sql_r("sqrt(abs(value))") + " AS a, " + sql_r("ln(1 + abs(value))") + " AS b, " + sql_r("1 / (1 + exp(-value / 100))") + " AS c, " + sql_r("pow(value / 100, 1.5)") + " AS d FROM events")
def op_fn_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("value")
    return EV(spark, sf_dir).select("event_id", r(F.sqrt(F.abs(v))).alias("a"), r(F.log1p(F.abs(v))).alias("b"), r(1 / (1 + F.exp(-v / 100))).alias("c"), r(F.pow(v / 100, F.lit(1.5))).alias("d"))


_EMB = "list_transform(embedding, lambda x: x::DOUBLE)"


@query(f"SELECT vec_id, CAST(len(embedding) AS INTEGER) AS n, {sql_r('list_sum(list_transform(embedding[1:8], lambda x: x::DOUBLE))')} AS s, {sql_r('list_max(list_transform(embedding, lambda x: x::DOUBLE))')} AS top FROM embeddings")
def op_fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = F.col("embedding").cast("array<double>")
    return T.table(spark, sf_dir, "embeddings").select("vec_id", F.size(e).alias("n"), r(F.aggregate(F.slice(e, 1, 8), F.lit(0.0), lambda a, x: a + x)).alias("s"), r(F.array_max(e)).alias("top"))


@query("SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks FROM events GROUP BY 1 HAVING count(*) FILTER (event_type = 'click') > 0")
def op_fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    per = EV(spark, sf_dir).groupBy("user_id", "event_type").count()
    made = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return made.select("user_id", F.element_at("m", "click").alias("clicks")).filter("clicks IS NOT NULL")


@query("SELECT event_id, CAST(props->>'$.k' AS BIGINT) AS k FROM events")
def op_fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("SELECT doc_id, md5(text) AS h FROM documents")
def op_fn_hash_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.table(spark, sf_dir, "documents").select("doc_id", F.md5("text").alias("h"))


_V2 = f"SELECT a.vec_id, list_transform(a.embedding, lambda x: x::DOUBLE) AS a, list_transform(b.embedding, lambda x: x::DOUBLE) AS b FROM embeddings AS a JOIN embeddings AS b ON b.vec_id = a.vec_id + 1"


def _vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = T.table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("a"))
    return e.join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("a").alias("b")), "vec_id")


@query(f"SELECT vec_id, {sql_r('a[1] + b[1]')} AS x, {sql_r('a[64] + b[64]')} AS y FROM ({_V2})")
def op_vec_add(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = V.vec_add(F.col("a"), F.col("b"))
    return _vectors(spark, sf_dir).select("vec_id", r(s[0]).alias("x"), r(s[63]).alias("y"))


@query(f"SELECT vec_id, {sql_r('list_dot_product(a, b)')} AS d FROM ({_V2})")
def op_vec_dot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vectors(spark, sf_dir).select("vec_id", r(V.vec_dot(F.col("a"), F.col("b"))).alias("d"))


@query(f"SELECT vec_id, {sql_r('sqrt(list_dot_product(a, a))')} AS n FROM ({_V2})")
def op_vec_norm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vectors(spark, sf_dir).select("vec_id", r(V.vec_norm(F.col("a"))).alias("n"))


@query(f"SELECT vec_id, {sql_r('list_dot_product(a, b) / (sqrt(list_dot_product(a, a)) * sqrt(list_dot_product(b, b)))')} AS c FROM ({_V2})")
def op_vec_cosine(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vectors(spark, sf_dir).select("vec_id", r(V.cosine(F.col("a"), F.col("b"))).alias("c"))


_SUMS = ", ".join(sql_r(f"sum(embedding[{i + 1}]::DOUBLE)", 4) + f" AS s{i}" for i in range(3))


@query(f"SELECT label, {_SUMS} FROM embeddings GROUP BY 1")
def op_vec_block(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = T.table(spark, sf_dir, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("e"))
    return e.groupBy("label").agg(V.vec_sum("e", 3).alias("s")).select("label", *[r(F.col("s")[i], 4).alias(f"s{i}") for i in range(3)])


@query("SELECT event_id, " + sql_r("1 / (1 + exp(-value / 50))") + " AS s FROM events")
def op_udf_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EV(spark, sf_dir).select("event_id", r(squash(F.col("value") / 50)).alias("s"))


@query(f"SELECT label, {_SUMS} FROM embeddings GROUP BY 1")
def op_udaf_vec_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = T.table(spark, sf_dir, "embeddings").select("label", F.slice(F.col("embedding").cast("array<double>"), 1, 3).alias("e"))
    return e.groupBy("label").agg(vec_sum_agg("e").alias("s")).select("label", *[r(F.col("s")[i], 4).alias(f"s{i}") for i in range(3)])


@query(f"SELECT src, dst, dw FROM (SELECT src, dst, w AS dw FROM ({q.EVENTS}) UNION ALL SELECT dst, src, w FROM ({q.EVENTS}))")
def op_udtf_half_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = T.interactions(spark, sf_dir)
    return e.lateralJoin(half_edges(F.col("kind").outer(), F.col("src").outer(), F.col("dst").outer(), F.col("w").outer()).toDF("a", "b", "dw")).select(F.col("a").alias("src"), F.col("b").alias("dst"), "dw")


@query(f"SELECT src AS node, sum(w) AS d FROM ({q.EVENT_EDGES}) GROUP BY src HAVING sum(w) >= 100")
def op_sql_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from dgprop.sql import register

    register(spark, sf_dir)
    return spark.sql("SELECT node, d FROM dg_degrees WHERE d >= 100")
