"""SQL for DuckDB that the queries' oracles are made of."""

from __future__ import annotations

from dgprop.functions.hashing import sql_uniform
from dgprop.workloads.registry import sql_r

U, I, C, P, S = (f"{k}000000000000" for k in range(1, 6))
EVENTS = f"SELECT event_id AS seq, epoch_us(ts) AS ts_us, user_id + {U} AS src, CAST(props->>'$.k' AS BIGINT) + {I} AS dst, 1.0::DOUBLE AS w, event_type, value FROM events"
TRADES = f"SELECT l_orderkey * 10 + l_linenumber AS seq, epoch_us(o_orderdate) AS ts_us, o_custkey + {C} AS src, l_partkey + {P} AS dst, 1.0::DOUBLE AS w, l_returnflag, o_orderstatus, epoch_us(l_shipdate) AS ship_us FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
SUPPLIES = TRADES.replace(f"l_partkey + {P}", f"l_suppkey + {S}")
DAY = 86_400_000_000


def mirrored(rows: str, columns: str = "w") -> str:
    return f"SELECT src, dst, {columns} FROM ({rows}) UNION ALL SELECT dst AS src, src AS dst, {columns} FROM ({rows}) WHERE src <> dst"


def edges_of(rows: str) -> str:
    """Both directions, weights summed."""
    return f"SELECT src, dst, sum(w) AS w FROM ({mirrored(rows)}) GROUP BY src, dst"


EVENT_EDGES = edges_of(EVENTS)
TRADE_EDGES = edges_of(TRADES)


def stepped(step: str = f"ts_us // {DAY}", rows: str = EVENTS, dw: str = "w") -> str:
    """Net deltas of both directions by step."""
    base = f"SELECT CAST({step} AS INTEGER) AS step, src, dst, {dw} AS dw FROM ({rows})"
    return f"SELECT step, src, dst, sum(dw) AS dw FROM ({mirrored(base, 'step, dw')}) GROUP BY step, src, dst HAVING abs(sum(dw)) > 1e-12"


def features(nodes: str, dim: int, seed: int = 0) -> str:
    text = f"concat('{seed}:', node, ':', dim)"
    return f"SELECT node, CAST(dim AS INTEGER) AS dim, {sql_uniform(text)} AS x FROM ({nodes}), range({dim}) AS dims(dim)"


def series(edges: str, dim: int, gamma: str, a: float, b: float, rounds: int, nodes: str | None = None, x: str | None = None, select: str | None = None, seed: int = 0) -> str:
    """Terms of the series by recursion; ``gamma`` is an expression of k."""
    nodes = nodes or "SELECT src AS node FROM e UNION SELECT dst AS node FROM e"
    return f"""WITH RECURSIVE e AS ({edges}), n AS ({nodes}), g AS (SELECT src AS node, sum(w) AS d FROM e GROUP BY src),
        x AS ({x or features('SELECT node FROM n', dim, seed)}),
        m AS (SELECT e.src, e.dst, e.w * pow(gs.d, -({b})) * pow(gd.d, -({a})) AS c FROM e JOIN g AS gs ON e.src = gs.node JOIN g AS gd ON e.dst = gd.node),
        t(k, node, dim, v) AS (SELECT 0, node, dim, x FROM x
            UNION ALL SELECT any_value(t.k) + 1, m.dst, t.dim, sum(t.v * m.c) FROM t JOIN m ON m.src = t.node WHERE t.k < {rounds} GROUP BY m.dst, t.dim)
        {select or f"SELECT node, dim, {sql_r(f'sum(v * ({gamma}))')} AS z FROM t GROUP BY node, dim"}"""


def geometric(g0: float, ratio: float) -> str:
    return f"{g0} * pow({ratio}, k)"


def series_by_step(deltas: str, dim: int, g0: float, ratio: float, beta: float, rounds: int, select: str | None = None) -> str:
    """The series on the graph of every step, with nodes and features of all steps."""
    return f"""WITH RECURSIVE dl AS ({deltas}), st AS (SELECT DISTINCT step FROM dl),
        e AS (SELECT st.step, src, dst, sum(dw) AS w FROM st JOIN dl ON dl.step <= st.step GROUP BY st.step, src, dst HAVING sum(dw) > 1e-12),
        n AS (SELECT src AS node FROM dl UNION SELECT dst AS node FROM dl), g AS (SELECT step, src AS node, sum(w) AS d FROM e GROUP BY step, src),
        x AS ({features('SELECT node FROM n', dim)}),
        m AS (SELECT e.step, e.src, e.dst, e.w * pow(gs.d, -({1 - beta})) * pow(gd.d, -({beta})) AS c FROM e JOIN g AS gs ON e.step = gs.step AND e.src = gs.node JOIN g AS gd ON e.step = gd.step AND e.dst = gd.node),
        t(k, step, node, dim, v) AS (SELECT 0, st.step, node, dim, x FROM x, st
            UNION ALL SELECT any_value(t.k) + 1, m.step, m.dst, t.dim, sum(t.v * m.c) FROM t JOIN m ON m.src = t.node AND m.step = t.step WHERE t.k < {rounds} GROUP BY m.step, m.dst, t.dim)
        {select or f"SELECT step, node, dim, {sql_r(f'sum(v * ({geometric(g0, ratio)}))', 5)} AS z FROM t GROUP BY step, node, dim"}"""


def push(edges: str, dim: int, g0: float, ratio: float, beta: float, rmax: float, rounds: int, select: str | None = None, nodes: str | None = None, x: str | None = None) -> str:
    """Rounds of push in scaled coordinates, all active nodes at once."""
    nodes = nodes or "SELECT src AS node FROM e UNION SELECT dst AS node FROM e"
    on = f"CASE WHEN abs(s.q) > {rmax} THEN s.q ELSE 0 END"
    return f"""WITH RECURSIVE e AS ({edges}), n AS ({nodes}), g0 AS (SELECT src AS node, sum(w) AS d FROM e GROUP BY src),
        g AS (SELECT n.node, coalesce(d, 1.0) AS d FROM n LEFT JOIN g0 USING (node)), x AS ({x or features('SELECT node FROM n', dim)}),
        m AS (SELECT src, dst, {ratio} * w / g.d AS c, false AS own FROM e JOIN g ON e.dst = g.node UNION ALL SELECT node, node, 0.0, true FROM n),
        s(k, node, dim, y, q) AS (SELECT 0, node, dim, 0.0::DOUBLE, x * pow(d, {beta} - 1) FROM x JOIN g USING (node)
            UNION ALL SELECT any_value(s.k) + 1, m.dst, s.dim, sum(CASE WHEN m.own THEN s.y + {g0} * ({on}) ELSE 0 END), sum(CASE WHEN m.own THEN s.q - ({on}) ELSE m.c * ({on}) END)
            FROM s JOIN m ON m.src = s.node WHERE s.k < {rounds} GROUP BY m.dst, s.dim)
        {select or f"SELECT node, dim, {sql_r(f'y * pow(d, 1 - {beta})')} AS z FROM s JOIN g USING (node) WHERE k = {rounds}"}"""
