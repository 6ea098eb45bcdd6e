"""Events, graphs, filters and push."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.operators import graph as G
from dgprop.operators import propagate as pr
from dgprop.operators.filters import FilterSpec, k_hop_only, restart_truncated
from dgprop.sources import tables as T
from dgprop.workloads import sqltext as q
from dgprop.workloads.registry import long_form, query, r, sql_r

RESTART, ALTERNATING = FilterSpec.restart(0.5), FilterSpec.alternating(0.5)


def event_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.weighted(G.mirrored(T.interactions(spark, sf_dir).select("src", "dst", "w")))


def trade_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.weighted(G.mirrored(T.trades(spark, sf_dir).select("src", "dst", "w")))


def daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.net_deltas(T.interactions(spark, sf_dir).withColumn("step", G.bucket()))


def random_x(edges: DataFrame, dim: int) -> DataFrame:
    return T.random_features(G.nodes_of(edges), dim)


# Events


@query(f"SELECT seq, ts_us, src, dst, w, event_type, value FROM ({q.EVENTS})")
def ev_from_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.interactions(spark, sf_dir).drop("kind")


@query(f"SELECT seq, ts_us, src, dst, w FROM ({q.TRADES})")
def ev_from_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.trades(spark, sf_dir).select("seq", "ts_us", "src", "dst", "w")


_F = f"SELECT * FROM ({q.SUPPLIES}) WHERE o_orderstatus = 'F'"
RETURNS = f"SELECT seq, ts_us, 'add_edge' AS kind, src, dst, w FROM ({_F}) UNION ALL SELECT seq, greatest(ts_us, ship_us) + {q.DAY}, 'del_edge', src, dst, w FROM ({_F}) WHERE l_returnflag = 'R'"


@query(RETURNS)
def ev_returns_as_deletes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.trades_with_returns(spark, sf_dir)


TTL = f"SELECT seq, ts_us, 'add_edge' AS kind, src, dst, w FROM ({q.EVENTS}) UNION ALL SELECT seq, ts_us + {7 * q.DAY}, 'del_edge', src, dst, w FROM ({q.EVENTS})"


@query(TTL)
def ev_ttl_deletes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.with_expiry(T.interactions(spark, sf_dir), 7)


@query(q.mirrored(q.EVENTS, "seq"))
def ev_symmetrised(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.mirrored(T.interactions(spark, sf_dir).select("src", "dst", "seq"))


@query(f"SELECT kind, count(*) AS n, min(ts_us) AS first_us, max(ts_us) AS last_us FROM ({RETURNS}) GROUP BY kind")
def ev_kind_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.trades_with_returns(spark, sf_dir).groupBy("kind").agg(F.count("*").alias("n"), F.min("ts_us").alias("first_us"), F.max("ts_us").alias("last_us"))


@query(f"SELECT CAST(dense_rank() OVER (ORDER BY ts_us) - 1 AS INTEGER) AS step, seq, src, dst FROM ({q.EVENTS})")
def ev_steps_by_timestamp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.by_timestamp(T.interactions(spark, sf_dir)).select("step", "seq", "src", "dst")


@query(f"SELECT CAST((row_number() OVER (ORDER BY ts_us, seq) - 1) // 500 AS INTEGER) AS step, seq, src, dst FROM ({q.EVENTS})")
def ev_steps_by_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.by_count(T.interactions(spark, sf_dir), 500).select("step", "seq", "src", "dst")


@query(q.stepped(rows=TTL, dw="CASE WHEN kind = 'add_edge' THEN w ELSE -w END"))
def ev_net_deltas(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.net_deltas(T.with_expiry(T.interactions(spark, sf_dir), 7).withColumn("step", G.bucket()))


_RD = q.stepped(rows=RETURNS, dw="CASE WHEN kind = 'add_edge' THEN w ELSE -w END")


@query(
    f"""WITH d AS ({_RD}), s AS (SELECT *, sum(dw) OVER w AS total FROM d WINDOW w AS (PARTITION BY src, dst ORDER BY step)),
    l AS (SELECT *, total - least(0.0, min(total) OVER (PARTITION BY src, dst ORDER BY step)) AS weight FROM s)
    SELECT step, src, dst, {sql_r("weight - coalesce(lag(weight) OVER (PARTITION BY src, dst ORDER BY step), 0.0)")} AS dw FROM l
    QUALIFY abs(weight - coalesce(lag(weight) OVER (PARTITION BY src, dst ORDER BY step), 0.0)) > 1e-12"""
)
def ev_clamped_deltas(spark: SparkSession, sf_dir: str) -> DataFrame:
    deltas = G.net_deltas(T.trades_with_returns(spark, sf_dir).withColumn("step", G.bucket()))
    return G.clamp_deltas(deltas)[0].withColumn("dw", r("dw"))


# Graphs


@query(q.EVENT_EDGES)
def gr_edges_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_edges(spark, sf_dir)


@query(f"SELECT src AS node, sum(w) AS d FROM ({q.TRADE_EDGES}) GROUP BY src")
def gr_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.degrees(trade_edges(spark, sf_dir))


_MID = "(SELECT CAST((min(step) + max(step)) // 2 AS INTEGER) FROM dl)"


def middle_step(deltas: DataFrame) -> int:
    return deltas.agg(F.floor((F.min("step") + F.max("step")) / 2)).head()[0]


@query(f"WITH dl AS ({q.stepped()}) SELECT src, dst, sum(dw) AS w FROM dl WHERE step <= {_MID} GROUP BY src, dst HAVING sum(dw) > 1e-12")
def gr_graph_at_t(spark: SparkSession, sf_dir: str) -> DataFrame:
    deltas = daily(spark, sf_dir)
    return G.graph_at(deltas, middle_step(deltas))


_MONTH = "year(make_timestamp(ts_us)) * 12 + month(make_timestamp(ts_us)) - 1"


@query(f"SELECT CAST({_MONTH} AS INTEGER) AS step, count(*) AS n, count(DISTINCT (src, dst)) AS n_edges FROM ({q.SUPPLIES}) GROUP BY 1")
def gr_snapshots_monthly(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = T.trades(spark, sf_dir, "supplier").withColumn("step", G.month())
    return rows.groupBy("step").agg(F.count("*").alias("n"), F.countDistinct("src", "dst").alias("n_edges"))


_LAST = "(SELECT max(step) FROM dl)"
_TWO = f"a AS (SELECT src, dst, sum(dw) AS w FROM dl WHERE step <= {_MID} GROUP BY src, dst HAVING sum(dw) > 1e-12), b AS (SELECT src, dst, sum(dw) AS w FROM dl GROUP BY src, dst HAVING sum(dw) > 1e-12)"
_TTLD = q.stepped(rows=TTL, dw="CASE WHEN kind = 'add_edge' THEN w ELSE -w END")


def _two_snapshots(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    deltas = G.net_deltas(T.with_expiry(T.interactions(spark, sf_dir), 7).withColumn("step", G.bucket()))
    middle = middle_step(deltas)
    return deltas, G.graph_at(deltas, middle), G.graph_at(deltas, middle + 5)


_TWO_TTL = f"a AS (SELECT src, dst, sum(dw) AS w FROM dl WHERE step <= {_MID} GROUP BY src, dst HAVING sum(dw) > 1e-12), b AS (SELECT src, dst, sum(dw) AS w FROM dl WHERE step <= {_MID} + 5 GROUP BY src, dst HAVING sum(dw) > 1e-12)"


@query(f"WITH dl AS ({_TTLD}), {_TWO_TTL} SELECT coalesce(a.src, b.src) AS src, coalesce(a.dst, b.dst) AS dst, coalesce(b.w, 0.0) - coalesce(a.w, 0.0) AS dw FROM a FULL JOIN b ON a.src = b.src AND a.dst = b.dst WHERE abs(coalesce(b.w, 0.0) - coalesce(a.w, 0.0)) > 1e-12")
def gr_snapshot_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, before, after = _two_snapshots(spark, sf_dir)
    return G.snapshot_diff(before, after)


@query(f"WITH dl AS ({_TTLD}), {_TWO_TTL} SELECT src, dst, w FROM b")
def gr_diff_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, before, after = _two_snapshots(spark, sf_dir)
    return G.apply_deltas(before, G.snapshot_diff(before, after))


@query(f"SELECT step, count(*) AS n_affected FROM (SELECT step, src AS node FROM ({q.stepped()}) UNION SELECT step, dst FROM ({q.stepped()})) GROUP BY step")
def gr_affected_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    deltas = daily(spark, sf_dir)
    ends = deltas.select("step", F.explode(F.array("src", "dst")).alias("node")).distinct()
    return ends.groupBy("step").agg(F.count("*").alias("n_affected"))


@query(f"WITH s AS (SELECT CAST(ts_us // {q.DAY} AS INTEGER) AS step, src, dst FROM ({q.EVENTS})) SELECT (SELECT count(*) FROM (SELECT src FROM s UNION SELECT dst FROM s)) AS n_nodes, count(*) AS n_temporal_edges, count(DISTINCT (src, dst)) AS n_edges, count(DISTINCT step) AS n_steps FROM s")
def gr_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.graph_stats(T.interactions(spark, sf_dir).select(G.bucket().alias("step"), "src", "dst"))


@query(f"WITH l AS (SELECT l_orderkey AS o, l_suppkey + {q.S} AS s FROM lineitem) SELECT CAST(year(o_orderdate) * 12 + month(o_orderdate) - 1 AS INTEGER) AS step, a.s AS src, b.s AS dst, count(*)::DOUBLE AS w FROM l AS a JOIN l AS b ON a.o = b.o AND a.s < b.s JOIN orders ON o_orderkey = a.o GROUP BY 1, 2, 3")
def gr_cosupplier_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.co_suppliers(spark, sf_dir)


@query("WITH l AS (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents), s AS (SELECT line FROM l WHERE length(line) > 20 GROUP BY line HAVING count(*) > 1) SELECT doc_id + 6000000000000 AS src, CAST('0x' || substr(md5(line), 1, 9) AS BIGINT) + 7000000000000 AS dst, 1.0::DOUBLE AS w FROM l JOIN s USING (line)")
def gr_doc_shared_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.shared_lines(spark, sf_dir)


@query("WITH l AS (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages) SELECT page_id + 8000000000000 AS src, CAST('0x' || substr(md5(href), 1, 9) AS BIGINT) + 9000000000000 AS dst, count(*)::DOUBLE AS w FROM l GROUP BY 1, 2")
def gr_page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.page_links(spark, sf_dir)


@query("SELECT a.conv_id * 1000 + a.turn + 11000000000000 AS src, a.conv_id * 1000 + a.turn + 11000000000001 AS dst, 1.0::DOUBLE AS w FROM conversations AS a JOIN conversations AS b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
def gr_conv_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.dialogue_paths(spark, sf_dir)


_VEC = "SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings"


@query(f"WITH v AS ({_VEC}), s AS (SELECT a.vec_id AS i, b.vec_id AS j, round(list_dot_product(a.e, b.e) / (sqrt(list_dot_product(a.e, a.e)) * sqrt(list_dot_product(b.e, b.e))), 9) AS c FROM v AS a JOIN v AS b ON a.vec_id <> b.vec_id) SELECT i + 10000000000000 AS src, j + 10000000000000 AS dst, 1.0::DOUBLE AS w FROM s QUALIFY row_number() OVER (PARTITION BY i ORDER BY c DESC, j) <= 5")
def gr_knn_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.nearest_vectors(spark, sf_dir)


# Filters by series


@query("SELECT node, dim, " + sql_r("x", 9) + f" AS x FROM ({q.features(f'SELECT src AS node FROM ({q.EVENT_EDGES}) GROUP BY src', 4)})")
def pr_random_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return random_x(event_edges(spark, sf_dir), 4).select("node", F.posexplode("x").alias("dim", "x")).withColumn("x", r("x", 9))


def _series(spark: SparkSession, sf_dir: str, gammas: list[float], a: float, b: float) -> DataFrame:
    edges = event_edges(spark, sf_dir)
    return long_form(pr.series_filter(edges, random_x(edges, 2), gammas, a, b, 2), "node")


def _series_query(name: str, spec: FilterSpec, rounds: int = 24) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _series(spark, sf_dir, spec.gammas(rounds + 1), spec.beta, 1 - spec.beta)

    run.__name__ = name
    query(q.series(q.EVENT_EDGES, 2, q.geometric(spec.g0, spec.ratio), spec.beta, 1 - spec.beta, rounds))(run)


_series_query("pr_series_low", RESTART)
_series_query("pr_series_high", ALTERNATING)
_series_query("pr_series_neg_power", FilterSpec.neg_power(0.5))
_series_query("pr_series_power", FilterSpec.power(0.5))
_series_query("pr_series_beta0", FilterSpec.restart(0.5, 0.0))
_series_query("pr_series_beta1", FilterSpec.restart(0.5, 1.0))


def _list_query(name: str, gammas: list[float], a: float, b: float) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _series(spark, sf_dir, gammas, a, b)

    run.__name__ = name
    query(q.series(q.EVENT_EDGES, 2, f"([{', '.join(map(str, gammas))}])[k + 1]", a, b, len(gammas) - 1))(run)


_list_query("pr_khop_only", k_hop_only(2), 0.5, 0.5)
_list_query("pr_restart_truncated", restart_truncated(4, 0.2), 0.5, 0.5)
_list_query("pr_general_ab", [0.4, 0.3, 0.2, 0.1], 0.3, 0.6)


# Push


def _push_query(name: str, spec: FilterSpec, rmax: float, rounds: int, fixed: bool, edges_sql: str, edges, dim: int = 2) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = edges(spark, sf_dir)
        done = pr.push(e, pr.init_state(random_x(e, dim), e, [spec], dim), [spec], rmax, dim, rounds if fixed else None)
        return long_form(done.readout(), "node")

    run.__name__ = name
    query(q.push(edges_sql, dim, spec.g0, spec.ratio, spec.beta, rmax, rounds))(run)


def document_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.weighted(G.mirrored(T.shared_lines(spark, sf_dir)))


_push_query("pr_push_fixed_rounds", RESTART, 1e-4, 4, True, q.EVENT_EDGES, event_edges)
_push_query("pr_push_converged", RESTART, 1e-4, 30, False, q.EVENT_EDGES, event_edges)
_push_query("pr_push_weighted_trade", FilterSpec.restart(0.5, 0.3), 1e-3, 20, False, q.TRADE_EDGES, trade_edges, 1)


@query(q.push(q.edges_of("SELECT doc_id + 6000000000000 AS src, CAST('0x' || substr(md5(line), 1, 9) AS BIGINT) + 7000000000000 AS dst, 1.0::DOUBLE AS w FROM (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) JOIN (SELECT line FROM (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) > 20 GROUP BY line HAVING count(*) > 1) USING (line)"), 2, 0.5, 0.5, 0.5, 1e-4, 30))
def pr_push_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = document_edges(spark, sf_dir)
    return long_form(pr.push(e, pr.init_state(random_x(e, 2), e, [RESTART], 2), [RESTART], 1e-4, 2).readout(), "node")


@query(
    "SELECT node, dim + 2 * band AS dim, z FROM ("
    + " UNION ALL ".join(f"SELECT node, dim, {b} AS band, z FROM ({q.push(q.EVENT_EDGES, 2, s.g0, s.ratio, s.beta, 1e-4, 30)})" for b, s in enumerate((RESTART, ALTERNATING)))
    + ")"
)
def pr_push_two_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    specs = [RESTART, ALTERNATING]
    done = pr.push(e, pr.init_state(random_x(e, 2), e, specs, 2), specs, 1e-4, 2)
    return long_form(done.both_bands(), "node")


def vector_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.weighted(G.mirrored(T.nearest_vectors(spark, sf_dir)))


@query()
def pr_push_embeddings_block(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = vector_edges(spark, sf_dir)
    x = T.table(spark, sf_dir, "embeddings").select((F.col("vec_id") + T.VECTOR).alias("node"), F.col("embedding").cast("array<double>").alias("x"))
    width = x.agg(F.max(F.size("x"))).head()[0] or 1
    return long_form(pr.push_blocks(e, x, RESTART, 1e-3, width), "node")


@query("SELECT 1 AS within")
def pr_identity_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    x = random_x(e, 2)
    done = pr.push(e, pr.init_state(x, e, [RESTART], 2), [RESTART], 1e-3, 2)
    return pr.identity_gap(done.state, e, x, RESTART, 2).select((F.col("gap") < 1e-12).cast("int").alias("within"))


@query("SELECT * FROM (VALUES ('low', 1, 1), ('high', 1, 1), ('power', 1, 1), ('neg_power', 1, 1)) AS t(filter, within, stopped)")
def pr_error_within_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    x, rmax = random_x(e, 1), 1e-3
    out = []
    specs = {"low": RESTART, "high": ALTERNATING, "power": FilterSpec.power(0.5, 0.3), "neg_power": FilterSpec.neg_power(0.5)}
    every = list(specs.values())
    done = pr.push(e, pr.init_state(x, e, every, 1), every, rmax, 1)
    exact = pr.series_filters(e, x, every, 40, 1)
    for s, (name, spec) in enumerate(specs.items()):
        largest = done.state.agg(F.coalesce(F.max(F.abs(f"q{s}_0")), F.lit(0.0)).alias("largest"))
        error = pr.estimate_error(done, exact[s], s).join(largest)
        out.append(error.select(F.lit(name).alias("filter"), (F.col("error") <= rmax * spec.mass).cast("int").alias("within"), (F.col("largest") <= rmax).cast("int").alias("stopped")))
    return reduce(DataFrame.unionByName, out)


_ON = "CASE WHEN abs(q) > 0.001 THEN 1 ELSE 0 END"


@query(q.push(q.EVENT_EDGES, 2, 0.5, 0.5, 0.5, 1e-3, 6, select=f"SELECT CAST(k AS INTEGER) AS round, CAST(count(DISTINCT CASE WHEN abs(q) > 0.001 THEN node END) AS BIGINT) AS active_nodes, CAST(sum({_ON}) AS BIGINT) AS active_cells, {sql_r('max(abs(q))')} AS max_abs_q, {sql_r('sum(abs(q) * d)', 4)} AS phi FROM s JOIN g USING (node) GROUP BY k"))
def pr_active_per_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_edges(spark, sf_dir)
    spec = RESTART
    state = pr.init_state(random_x(e, 2), e, [spec], 2)
    done = pr.push(e, state, [spec], 1e-3, 2, 6)
    stats = list(done.stats)
    while len(stats) < 7:  # nothing changes after the last round
        stats.append(stats[-1] | {"round": len(stats)})
    rows = [(s["round"], s["active_nodes"], s["active_cells"], s["max_abs_q"], s["phi"]) for s in stats]
    made = spark.createDataFrame(rows, "round int, active_nodes bigint, active_cells bigint, max_abs_q double, phi double")
    return made.withColumns({"max_abs_q": r("max_abs_q"), "phi": r("phi", 4)})
