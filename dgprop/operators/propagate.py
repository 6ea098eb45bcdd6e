"""Filters by truncated series and by residual-driven push.

State is kept in scaled coordinates, estimate ``y = p / D^(1-beta)`` and residual
``q = r / D^(1-beta)``: then the activity test does not depend on degrees, a push
over an edge is ``q(v) += ratio * w / D(v) * q(u)`` for every beta, and a change of
degree leaves the estimates as they are.  D is the degree, or 1 where it is 0.

A round pushes all active nodes at once.  With state and adjacency partitioned by
node, a round has one exchange: the sums by receiving node.  Division by D comes
after the sum, so that the adjacency never has to be rewritten.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dgprop.operators.filters import FilterSpec
from dgprop.plans.lineage import cut, fixed_plans

#: Feature columns that one loop carries; more are run as further loops.
BLOCK = 16


def safe_degree(d: str = "d") -> Column:
    return F.when(F.col(d) > 0, F.col(d)).otherwise(F.lit(1.0))


def with_degree(features: DataFrame, edges: DataFrame) -> DataFrame:
    """node, x and D; nodes without edges have D = 1."""
    d = edges.groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("d"))
    return features.join(d, "node", "left").select("node", "x", F.coalesce(safe_degree(), F.lit(1.0)).alias("D"))


def series_filter(edges: DataFrame, features: DataFrame, gammas: list[float], a: float, b: float, dim: int, cut_every: int = 1) -> DataFrame:
    """node and z = sum of gammas[k] * (D^-a A D^-b)^k x, term by term."""
    base = with_degree(features, edges)
    cols = [f"t{i}" for i in range(dim)]
    terms = base.select("node", "D", *[F.col("x")[i].alias(c) for i, c in enumerate(cols)], *[(F.col("x")[i] * gammas[0]).alias(f"z{i}") for i in range(dim)])
    adj = edges.select("src", "dst", "w")
    spark = edges.sparkSession
    with fixed_plans(spark):
        adj, terms = cut(adj.repartition("src")), cut(terms.repartition("node"))
        for k, gamma in enumerate(gammas[1:], 1):
            sent = terms.select("node", *[(F.col(c) * F.pow("D", F.lit(-b))).alias(c) for c in cols]).join(adj, F.col("node") == F.col("src"))
            got = sent.groupBy("dst").agg(*[F.sum(F.col("w") * F.col(c)).alias(f"s{i}") for i, c in enumerate(cols)])
            new = [(F.coalesce(F.col(f"s{i}"), F.lit(0.0)) * F.pow("D", F.lit(-a))) for i in range(dim)]
            terms = terms.join(got, F.col("node") == F.col("dst"), "left").select("node", "D", *[n.alias(c) for n, c in zip(new, cols, strict=True)], *[(F.col(f"z{i}") + gamma * n).alias(f"z{i}") for i, n in enumerate(new)])
            if k % cut_every == 0:
                terms = cut(terms)
        return cut(terms.select("node", F.array(*[f"z{i}" for i in range(dim)]).alias("z")))


def series_filters(edges: DataFrame, features: DataFrame, specs: list[FilterSpec], n_terms: int, dim: int) -> list[DataFrame]:
    """The truncated series of each filter as node and z, all in one loop over the same edges.

    Terms are kept divided by the degree to the power of one less beta, where all filters have the same matrix.
    """
    base = with_degree(features, edges)
    gammas = [spec.gammas(n_terms) for spec in specs]
    at = [(s, i) for s in range(len(specs)) for i in range(dim)]
    terms = base.select("node", "D", *[(F.col("x")[i] * F.pow("D", F.lit(specs[s].beta - 1))).alias(f"t{s}_{i}") for s, i in at])
    terms = terms.select("*", *[(F.col(f"t{s}_{i}") * gammas[s][0]).alias(f"z{s}_{i}") for s, i in at])
    with fixed_plans(edges.sparkSession):
        adj, terms = cut(edges.select("src", "dst", "w").repartition("src")), cut(terms.repartition("node"))
        for k in range(1, n_terms):
            got = terms.join(adj, F.col("node") == F.col("src")).groupBy("dst").agg(*[F.sum(F.col("w") * F.col(f"t{s}_{i}")).alias(f"s{s}_{i}") for s, i in at])
            new = {(s, i): F.coalesce(F.col(f"s{s}_{i}"), F.lit(0.0)) / F.col("D") for s, i in at}
            terms = terms.join(got, F.col("node") == F.col("dst"), "left").select("node", "D", *[new[s, i].alias(f"t{s}_{i}") for s, i in at], *[(F.col(f"z{s}_{i}") + gammas[s][k] * new[s, i]).alias(f"z{s}_{i}") for s, i in at])
            terms = cut(terms)
    return [terms.select("node", F.array(*[F.col(f"z{s}_{i}") * F.pow("D", F.lit(1 - spec.beta)) for i in range(dim)]).alias("z")) for s, spec in enumerate(specs)]


def terms_needed(spec: FilterSpec, tolerance: float, largest: float = 1.0) -> int:
    """Powers after which the rest of the series is below the tolerance."""
    return max(1, math.ceil(math.log(tolerance / (spec.mass * max(largest, 1e-300))) / math.log(abs(spec.ratio)))) + 1


def exact_filter(edges: DataFrame, features: DataFrame, spec: FilterSpec, dim: int, tolerance: float = 1e-12) -> DataFrame:
    largest = features.agg(F.max(F.array_max(F.transform("x", lambda v: F.abs(v))))).head()[0] or 1.0
    return series_filter(edges, features, spec.gammas(terms_needed(spec, tolerance, largest)), spec.beta, 1 - spec.beta, dim)


@dataclass
class PushResult:
    """State (node, D, y<s>_<i>, q<s>_<i>) and one row of counts for each round."""

    state: DataFrame
    specs: list[FilterSpec]
    dim: int
    stats: list[dict] = field(default_factory=list)

    def readout(self, s: int = 0) -> DataFrame:
        """node and z of one filter."""
        power = F.pow("D", F.lit(1 - self.specs[s].beta))
        return self.state.select("node", F.array(*[F.col(f"y{s}_{i}") * power for i in range(self.dim)]).alias("z"))

    def both_bands(self) -> DataFrame:
        """node and the representations of all filters, one after the other."""
        parts = [F.array(*[F.col(f"y{s}_{i}") * F.pow("D", F.lit(1 - spec.beta)) for i in range(self.dim)]) for s, spec in enumerate(self.specs)]
        return self.state.select("node", F.concat(*parts).alias("z"))


def cells(prefix: str, specs: list[FilterSpec], dim: int) -> list[str]:
    return [f"{prefix}{s}_{i}" for s in range(len(specs)) for i in range(dim)]


def init_state(features: DataFrame, edges: DataFrame, specs: list[FilterSpec], dim: int) -> DataFrame:
    """Estimate 0, residual the features."""
    base = with_degree(features, edges)
    q = [(F.col("x")[i] * F.pow("D", F.lit(spec.beta - 1))).alias(f"q{s}_{i}") for s, spec in enumerate(specs) for i in range(dim)]
    return base.select("node", "D", *[F.lit(0.0).alias(c) for c in cells("y", specs, dim)], *q)


def active_part(column: str, rmax: float) -> Column:
    return F.when(F.abs(F.col(column)) > rmax, F.col(column)).otherwise(F.lit(0.0))


def push_round(state: DataFrame, adj: DataFrame, specs: list[FilterSpec], rmax: float, dim: int) -> DataFrame:
    """One round: every node hands on the residuals that are too large."""
    qs = cells("q", specs, dim)
    sizes = F.greatest(*[F.abs(F.col(q)) for q in qs]) if len(qs) > 1 else F.abs(F.col(qs[0]))
    frontier = state.filter(sizes > rmax).select("node", *[active_part(q, rmax).alias("a" + q[1:]) for q in qs])
    # Rows without an active cell in a column add 0 to it.
    got = frontier.join(adj, F.col("node") == F.col("src")).groupBy("dst").agg(*[F.sum(F.col("w") * F.col("a" + q[1:])).alias("s" + q[1:]) for q in qs])
    out = []
    for s, spec in enumerate(specs):
        for i in range(dim):
            out.append((F.col(f"y{s}_{i}") + spec.g0 * active_part(f"q{s}_{i}", rmax)).alias(f"y{s}_{i}"))
    for s, spec in enumerate(specs):
        for i in range(dim):
            # The pushed residual goes before the neighbours' shares arrive, so a self-loop's share stays.
            kept = F.when(F.abs(F.col(f"q{s}_{i}")) > rmax, F.lit(0.0)).otherwise(F.col(f"q{s}_{i}"))
            out.append((kept + spec.ratio * F.coalesce(F.col(f"s{s}_{i}"), F.lit(0.0)) / F.col("D")).alias(f"q{s}_{i}"))
    return state.join(got, F.col("node") == F.col("dst"), "left").select("node", "D", *out)


def round_stats(state: DataFrame, degrees_in_edges: DataFrame, specs: list[FilterSpec], rmax: float, dim: int) -> dict:
    """Active nodes and cells, edges that their push will touch, the largest residual, and the potential."""
    qs = cells("q", specs, dim)
    is_on = [F.when(F.abs(F.col(q)) > rmax, 1).otherwise(0) for q in qs]
    on = sum(is_on[1:], is_on[0])
    size = F.greatest(*[F.abs(F.col(q)) for q in qs]) if len(qs) > 1 else F.abs(F.col(qs[0]))
    row = state.join(degrees_in_edges, "node", "left").agg(
        F.coalesce(F.sum(F.when(on > 0, 1).otherwise(0)), F.lit(0)).alias("active_nodes"),
        F.coalesce(F.sum(on), F.lit(0)).alias("active_cells"),
        F.coalesce(F.sum(F.when(on > 0, F.coalesce("n_edges", F.lit(0))).otherwise(0)), F.lit(0)).alias("edges_touched"),
        F.coalesce(F.max(size), F.lit(0.0)).alias("max_abs_q"),
        F.coalesce(F.sum(sum([F.abs(F.col(q)) for q in qs[1:]], F.abs(F.col(qs[0]))) * F.col("D")), F.lit(0.0)).alias("phi"),
    )
    return row.head().asDict()


def push(edges: DataFrame, state: DataFrame, specs: list[FilterSpec], rmax: float, dim: int, max_rounds: int | None = None) -> PushResult:
    """Rounds until no residual is above ``rmax``, or ``max_rounds`` of them."""
    if rmax <= 0 and max_rounds is None:
        raise ValueError("a tolerance of 0 needs a number of rounds")
    if dim * len(specs) > 2 * BLOCK:
        raise ValueError("too many columns for one loop: split the features into blocks")
    with fixed_plans(edges.sparkSession):
        adj = cut(edges.select("src", "dst", "w").repartition("src"))
        out_edges = cut(adj.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("n_edges")))
        state = cut(state.repartition("node"))
        stats: list[dict] = []
        while True:
            now = round_stats(state, out_edges, specs, rmax, dim) | {"round": len(stats)}
            stats.append(now)
            if now["active_nodes"] == 0 or (max_rounds is not None and now["round"] >= max_rounds):
                return PushResult(state, specs, dim, stats)
            state = cut(push_round(state, adj, specs, rmax, dim))


def push_blocks(edges: DataFrame, features: DataFrame, spec: FilterSpec, rmax: float, dim: int, block: int = BLOCK) -> DataFrame:
    """node and z for any number of columns: blocks are loops of their own, and columns do not depend on each other."""
    out = None
    for first in range(0, dim, block):
        n = min(block, dim - first)
        part = features.select("node", F.slice("x", first + 1, n).alias("x"))
        z = push(edges, init_state(part, edges, [spec], n), [spec], rmax, n).readout()
        out = z if out is None else out.join(z.withColumnRenamed("z", "z2"), "node").select("node", F.concat("z", "z2").alias("z"))
    return out


def identity_gap(state: DataFrame, edges: DataFrame, features: DataFrame, spec: FilterSpec, dim: int, s: int = 0) -> DataFrame:
    """The largest distance between both sides of y + g0 q = g0 x D^(beta-1) + (ratio / D) sum of w y over neighbours."""
    sums = state.join(edges, F.col("node") == F.col("src")).groupBy("dst").agg(*[F.sum(F.col("w") * F.col(f"y{s}_{i}")).alias(f"n{i}") for i in range(dim)])
    both = state.join(features, "node").join(sums, F.col("node") == F.col("dst"), "left")
    gaps = [F.abs(F.col(f"y{s}_{i}") + spec.g0 * F.col(f"q{s}_{i}") - spec.g0 * F.col("x")[i] * F.pow("D", F.lit(spec.beta - 1)) - spec.ratio / F.col("D") * F.coalesce(F.col(f"n{i}"), F.lit(0.0))) for i in range(dim)]
    return both.agg(F.max(F.greatest(*gaps) if dim > 1 else gaps[0]).alias("gap"))


def estimate_error(result: PushResult, exact: DataFrame, s: int = 0) -> DataFrame:
    """The largest |z - exact| / D^(1-beta): at most the tolerance times the filter's mass."""
    spec = result.specs[s]
    both = result.readout(s).join(exact.withColumnRenamed("z", "e"), "node").join(result.state.select("node", "D"), "node")
    gap = F.array_max(F.zip_with("z", "e", lambda a, b: F.abs(a - b)))
    return both.agg(F.max(gap / F.pow("D", F.lit(1 - spec.beta))).alias("error"))
