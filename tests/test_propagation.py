"""Worked example, identity, bound and repair on small graphs."""

import time

import numpy as np
import pytest

from dgprop.operators import propagate as pr
from dgprop.operators.filters import FilterSpec
from dgprop.operators.graph import clamp_deltas, graph_at, net_deltas, snapshot_diff
from dgprop.operators import timeline
from dgprop.operators.kernel import Flow, LocalGraph
from dgprop.operators.timeline import run_timeline
from dgprop.operators.update import repair, repair_pull
from dgprop.plans.lineage import count_exchanges, cut, fixed_plans, plan_text

LOW, HIGH = FilterSpec.restart(0.2), FilterSpec.alternating(0.2)
EVENTS = [(1, "add_edge", 1, 5), (1, "add_edge", 2, 4), (2, "add_edge", 1, 4), (2, "add_edge", 3, 4), (3, "add_edge", 3, 5), (4, "del_edge", 3, 4), (5, "add_edge", 1, 3)]
DEGREES = {1: [1, 1, 0, 1, 1], 2: [2, 1, 1, 3, 1], 3: [2, 1, 2, 3, 2], 4: [2, 1, 1, 2, 2], 5: [3, 1, 2, 2, 2]}
# The exact filters of x = (1, 2, 3, 4, 5) at each step.
EXACT = {
    1: ([2.777778, 2.888889, 0.6, 3.111111, 3.222222], [-1.666667, -0.666667, 0.6, 1.333333, 2.333333]),
    2: ([3.005372, 2.207319, 2.407319, 3.91296, 2.700095], [-1.130258, -0.169773, 0.030227, 1.233594, 1.639371]),
    3: ([2.75694, 2.112216, 3.15694, 3.707056, 3.365552], [-0.824811, -0.200859, -0.424811, 1.300897, 1.499849]),
    4: ([3.006317, 2.254118, 2.714614, 3.277649, 3.738144], [-0.993683, -0.407931, -0.280191, 1.428234, 1.555973]),
    5: ([3.207342, 2.125164, 2.936332, 3.049688, 3.222046], [-0.649739, -0.253807, 0.38967, 1.155779, 1.056336]),
}


@pytest.fixture(scope="module")
def example(spark):
    events = spark.createDataFrame([(t, k, a, b, 1.0) for t, k, a, b in EVENTS], "step int, kind string, src bigint, dst bigint, w double")
    x = spark.createDataFrame([(i, [float(i)]) for i in range(1, 6)], "node bigint, x array<double>")
    return cut(net_deltas(events)), cut(x)


@pytest.mark.parametrize("local", [True, False])
@pytest.mark.parametrize("strategy", ["incremental", "recompute"])
def test_worked_example(example, local, strategy):
    deltas, x = example
    if not local and strategy == "recompute":
        pytest.skip("same loop")
    rows = run_timeline(deltas, x, [LOW, HIGH], 1e-9, 1, strategy=strategy, local=local).representations.collect()
    assert len(rows) == 25
    for r in rows:
        assert r["z"] == pytest.approx([EXACT[r["step"]][b][r["node"] - 1] for b in (0, 1)], abs=2e-6)


def test_degrees_and_transient_edge(example):
    deltas, _ = example
    for step, want in DEGREES.items():
        d = {r["src"]: r["d"] for r in graph_at(deltas, step).groupBy("src").sum("w").withColumnRenamed("sum(w)", "d").collect()}
        assert [d.get(i, 0) for i in range(1, 6)] == want
    diff = snapshot_diff(graph_at(deltas, 0), graph_at(deltas, 5)).collect()
    assert {(r["src"], r["dst"]) for r in diff if r["src"] < r["dst"]} == {(1, 3), (1, 4), (1, 5), (2, 4), (3, 5)}


@pytest.mark.parametrize("strategy", ["per_event", "auto"])
def test_per_event_and_auto_agree(example, strategy):
    deltas, x = example
    for r in run_timeline(deltas, x, [LOW], 1e-9, 1, strategy=strategy).representations.collect():
        assert r["z"][0] == pytest.approx(EXACT[r["step"]][0][r["node"] - 1], abs=2e-6)
    counts, found = [], []
    for local in (True, False):
        done = run_timeline(deltas, x, [LOW], 0.2, 1, strategy=strategy, local=local)
        rows = {(r["step"], r["node"]): r["z"][0] for r in done.representations.collect()}
        assert len(rows) == 25
        found.append(rows)
        counts.append([(r["step"], r["rounds"], r["pushes"], r["edges_touched"], r["affected_nodes"], r["deltas"], r["emitted"]) for r in done.stats.orderBy("step").collect()])
    assert counts[0] == counts[1]
    assert all(z == pytest.approx(found[1][k], abs=1e-9) for k, z in found[0].items())


@pytest.mark.parametrize(("specs", "dim", "paths"), [([LOW], 172, [True]), ([LOW, HIGH], 128, [True]), ([LOW, HIGH], 18, [True, False])])
def test_features_of_any_width(spark, example, specs, dim, paths):
    """Blocks of columns give what columns give that are run alone, and both paths the same rows and counts."""
    deltas, _ = example
    rng = np.random.default_rng(0)
    values = rng.normal(size=(5, dim))
    x = cut(spark.createDataFrame([(i + 1, v.tolist()) for i, v in enumerate(values)], "node bigint, x array<double>"))
    found, counts = [], []
    for local in paths:
        done = run_timeline(deltas.filter("step <= 1"), x, specs, 1.0, dim, local=local)
        found.append({(r["step"], r["node"]): r["z"] for r in done.representations.collect()})
        counts.append([(r["step"], r["rounds"], r["pushes"], r["edges_touched"], r["emitted"]) for r in done.stats.orderBy("step").collect()])
    assert counts[0] == counts[-1] and found[0].keys() == found[-1].keys()
    for k, z in found[0].items():
        assert len(z) == dim * len(specs) and z == pytest.approx(found[-1][k], abs=1e-9)
    c = dim - 1
    alone = cut(spark.createDataFrame([(i + 1, [float(v[c])]) for i, v in enumerate(values)], "node bigint, x array<double>"))
    for r in run_timeline(deltas.filter("step <= 1"), alone, specs, 1.0, 1, local=True).representations.collect():
        assert r["z"] == pytest.approx([found[0][r["step"], r["node"]][s * dim + c] for s in range(len(specs))], abs=1e-9)
    assert run_timeline(deltas.limit(0), x.limit(0), specs, 1.0, dim, local=paths[-1]).representations.count() == 0


def random_graph(rng, n=12, dim=2):
    specs = [FilterSpec(rng.choice([0.3, 1.0]), r, b) for r, b in ((0.7, 0.5), (-0.6, 0.0), (0.5, 1.0))]
    return LocalGraph(np.arange(n), rng.normal(size=(n, dim)), specs)


@pytest.mark.parametrize("seed", range(12))
def test_identity_and_bound_over_random_batches(seed):
    """Adds, deletes, weights, self-loops, features, last edges: the identity holds, the error stays in the bound."""
    rng = np.random.default_rng(seed)
    g, rmax = random_graph(rng), 1e-3
    g.reset()
    for _ in range(6):
        a, b = rng.integers(0, 12, 5), rng.integers(0, 12, 5)
        w = rng.integers(1, 4, 5).astype(float)
        src, dst, dw = [], [], []
        for i, j, v in zip(a, b, w, strict=True):
            v = -g.weight[i, j] if (i, j) in g.weight and rng.random() < 0.5 and (i, j) not in zip(src, dst, strict=True) else v
            for s, t in {(i, j), (j, i)}:
                src, dst, dw = [*src, s], [*dst, t], [*dw, v]
        new = {int(rng.integers(0, 12)): rng.normal(size=2)} if rng.random() < 0.5 else None
        touched = g.apply(np.array(src), np.array(dst), np.array(dw), new)
        assert touched <= 2 * len(src) + 1
        assert g.identity_gap() < 1e-10
        g.push(rmax)
        assert g.identity_gap() < 1e-10
        assert np.abs(g.q).max() <= rmax
        error = np.abs(g.read() - g.exact())
        for s, spec in enumerate(g.specs):
            assert (error[:, 2 * s : 2 * s + 2] <= rmax * spec.mass * g.safe[:, None] ** (1 - spec.beta) + 1e-12).all()


def test_schedules_agree_within_the_bound():
    rng = np.random.default_rng(5)
    one, two = random_graph(rng), random_graph(np.random.default_rng(5))
    src = np.concatenate((np.arange(11), np.arange(1, 12)))
    dst = np.concatenate((np.arange(1, 12), np.arange(11)))
    for g in (one, two):
        g.apply(src, dst, np.ones(22))
        g.reset()
    one.push(1e-4)
    assert two.push_in_turn(1e-4) > 0
    for s, spec in enumerate(one.specs):
        gap = np.abs(one.read() - two.read())[:, 2 * s : 2 * s + 2]
        assert (gap <= 2e-4 * spec.mass * one.safe[:, None] ** (1 - spec.beta) + 1e-12).all()


def test_constant_vector_is_fixed(spark):
    """x = d^(1-beta) is an eigenvector: the filter multiplies it by its response at 1."""
    edges = [(0, i) for i in range(1, 6)] + [(1, 2)]
    e = spark.createDataFrame([(a, b, 1.0) for a, b in edges] + [(b, a, 1.0) for a, b in edges], "src bigint, dst bigint, w double")
    d = {r["src"]: r["n"] for r in e.groupBy("src").count().withColumnRenamed("count", "n").collect()}
    x = spark.createDataFrame([(i, [float(d[i]) ** 0.5]) for i in d], "node bigint, x array<double>")
    done = pr.push(e, pr.init_state(x, e, [LOW], 1), [LOW], 1e-10, 1)
    for r in done.readout().collect():
        assert r["z"][0] == pytest.approx(d[r["node"]] ** 0.5 * LOW.response(1.0), abs=1e-8)


def test_edge_cases(spark):
    none = spark.createDataFrame([], "src bigint, dst bigint, w double")
    x = spark.createDataFrame([(7, [2.0])], "node bigint, x array<double>")
    done = pr.push(none, pr.init_state(x, none, [LOW], 1), [LOW], 1e-6, 1)
    assert done.readout().collect()[0]["z"] == [pytest.approx(0.4)]
    loop = spark.createDataFrame([(7, 7, 3.0)], "src bigint, dst bigint, w double")
    done = pr.push(loop, pr.init_state(x, loop, [LOW], 1), [LOW], 1e-9, 1)
    assert done.readout().collect()[0]["z"][0] == pytest.approx(2.0, abs=1e-7)
    empty = spark.createDataFrame([], "node bigint, x array<double>")
    assert pr.push(none, pr.init_state(empty, none, [LOW], 1), [LOW], 1e-6, 1).readout().count() == 0
    with pytest.raises(ValueError):
        pr.push(none, pr.init_state(x, none, [LOW], 1), [LOW], 0.0, 1)
    for bad in (0.0, 1.0, -1.0):
        with pytest.raises(ValueError):
            FilterSpec(1.0, bad)


def test_repair_on_frames(spark, example):
    deltas, x = example
    old, new = cut(graph_at(deltas, 3)), cut(deltas.filter("step IN (4, 5)").groupBy("src", "dst").sum("dw").withColumnRenamed("sum(dw)", "dw"))
    state = pr.push(old, pr.init_state(x, old, [LOW, HIGH], 1), [LOW, HIGH], 1e-4, 1).state
    after = cut(graph_at(deltas, 5))
    one = cut(repair(state, new, old, x, [LOW, HIGH], 1))
    for s, spec in enumerate((LOW, HIGH)):
        assert pr.identity_gap(one, after, x, spec, 1, s).head()[0] < 1e-12
    touched = new.select("src").withColumnRenamed("src", "node").distinct()
    two = {r["node"]: r for r in repair_pull(state, after, touched, x, [LOW, HIGH], 1).collect()}
    for r in one.collect():
        assert (r["q0_0"], r["q1_0"]) == (pytest.approx(two[r["node"]]["q0_0"], abs=1e-12), pytest.approx(two[r["node"]]["q1_0"], abs=1e-12))


def test_over_deleted_edges_are_refused(spark):
    d = spark.createDataFrame([(1, 1, 2, -1.0), (2, 1, 2, 2.0), (3, 1, 2, -5.0), (4, 1, 2, 1.0)], "step int, src bigint, dst bigint, dw double")
    kept, refused = clamp_deltas(d)
    assert sorted((r["step"], r["dw"]) for r in kept.collect()) == [(2, 2.0), (3, -2.0), (4, 1.0)]
    assert sorted((r["step"], r["dw"]) for r in refused.collect()) == [(1, -1.0), (3, -3.0)]


def test_filters_share_one_loop(spark, example, sf, monkeypatch):
    """Series of filters with different powers of the degree are those of each for itself; the query of the bound pushes all at once."""
    from dgprop.operators.graph import mirrored, weighted
    from dgprop.workloads import load

    _, x = example
    e = cut(weighted(mirrored(spark.createDataFrame([(1, 5, 1.0), (2, 4, 2.0), (1, 4, 1.0), (3, 4, 0.5)], "src bigint, dst bigint, w double"))))
    specs = [LOW, HIGH, FilterSpec.power(0.5, 0.3), FilterSpec.neg_power(0.5)]
    read = lambda df: {r["node"]: r["z"] for r in df.collect()}
    for spec, z in zip(specs, pr.series_filters(e, x, specs, 12, 1), strict=True):
        alone, got = read(pr.series_filter(e, x, spec.gammas(12), spec.beta, 1 - spec.beta, 1)), read(z)
        assert got.keys() == alone.keys() and all(abs(got[n][0] - alone[n][0]) < 1e-12 for n in got)
    loops, push = [], pr.push
    monkeypatch.setattr(pr, "push", lambda *args: loops.append(args) or push(*args))
    got = sorted(tuple(r) for r in load()[0]["pr_error_within_bound"](spark, sf).collect())
    assert got == [("high", 1, 1), ("low", 1, 1), ("neg_power", 1, 1), ("power", 1, 1)] and len(loops) == 1


def test_a_round_has_one_exchange(spark, example):
    deltas, x = example
    e = graph_at(deltas, 5)
    with fixed_plans(spark):
        adj, state = cut(e.repartition("src")), cut(pr.init_state(x, e, [LOW], 1).repartition("node"))
        one = pr.push_round(state, adj, [LOW], 1e-3, 1)
        assert count_exchanges(one) == 1
        again = pr.push_round(cut(one), adj, [LOW], 1e-3, 1)
        assert count_exchanges(again) == 1
        assert "Python" not in plan_text(again) and "Cartesian" not in plan_text(again)


def test_embeddings_are_pushed_in_all_columns(spark, sf, monkeypatch):
    from dgprop.workloads import graphs

    asked = []
    monkeypatch.setattr(graphs.pr, "push_blocks", lambda e, x, spec, rmax, dim: asked.append(dim) or x.withColumnRenamed("x", "z"))
    got = graphs.pr_push_embeddings_block(spark, sf)
    held = spark.read.parquet(f"{sf}/embeddings.parquet").selectExpr("max(size(embedding))", "sum(size(embedding))").head()
    assert asked == [held[0]] and got.count() == held[1]


def test_arrays_of_many_edges_are_pushed_in_time():
    """Twenty steps of a graph of 100,000 half-edges; sums by place took several times as long."""
    rng = np.random.default_rng(1)
    src, dst = rng.integers(0, 1000, 50_000), rng.integers(1000, 1100, 50_000)
    g = LocalGraph(np.arange(1100), rng.normal(size=(1100, 8)), [FilterSpec.restart(0.2), FilterSpec.alternating(0.2)])
    began = time.process_time()
    for k in range(20):
        a, b = src[k::20], dst[k::20]
        g.apply(np.concatenate((a, b)), np.concatenate((b, a)), np.ones(2 * len(a)))
        if k == 0:
            g.reset()
        g.push(1e-4)
    assert g.identity_gap() < 1e-9 and time.process_time() - began < 5


def test_an_edge_that_is_used_up_starts_anew_in_the_same_batch():
    g = LocalGraph(np.arange(3), np.ones((3, 1)), [FilterSpec.restart(0.2)])
    g.apply(np.array([0, 1, 0, 1]), np.array([1, 0, 1, 0]), np.array([1.0, 1.0, 2.0, 2.0]))
    assert g.weight == {(0, 1): 3.0, (1, 0): 3.0}
    g.apply(np.array([0, 1, 0, 1, 1, 2]), np.array([1, 0, 1, 0, 2, 1]), np.array([-4.0, -4.0, 1.0, 1.0, 5.0, 5.0]))
    assert g.weight == {(0, 1): 1.0, (1, 0): 1.0, (1, 2): 5.0, (2, 1): 5.0}


def test_products_over_hubs_give_the_plain_sums():
    """A star, a ring and a one-way edge: hubs' edges go through products, the others one by one."""
    rng, n = np.random.default_rng(1), 300
    pairs = {(0, i) for i in range(1, 200)} | {(i, 0) for i in range(1, 200)} | {(1, i) for i in range(2, 150)} | {(i, 1) for i in range(2, 150)} | {(i, (i + 1) % n) for i in range(2, n)}
    src, dst = (np.array(v) for v in zip(*sorted(pairs), strict=True))
    w = rng.uniform(0.5, 2, len(src))
    flow = Flow(n, src, dst, w)
    assert flow.hubs.tolist() == [0, 1]
    for active in (np.arange(n), np.array([5, 250])):
        values = np.zeros((n, 3))
        values[active] = rng.normal(size=(len(active), 3))
        want = np.zeros((n, 3))
        np.add.at(want, dst, w[:, None] * values[src])
        assert flow.sums(values, active) == pytest.approx(want, abs=1e-12)


@pytest.mark.parametrize("strategy", ["incremental", "recompute", "auto"])
def test_columns_in_tasks_of_their_own_give_the_same_rows(spark, monkeypatch, strategy):
    edges = [(s, a, b) for s in range(4) for a, b in ((s, s + 1), (s, 7), (7, 8))]
    deltas = spark.createDataFrame([(s, x, y, 1.0) for s, a, b in edges for x, y in ((a, b), (b, a))], "step int, src bigint, dst bigint, dw double")
    x = spark.createDataFrame([(i, [float(i % 3) - 1, float(i % 4) - 1]) for i in range(9)], "node bigint, x array<double>")
    for emit in ("all", "changed", "last"):
        got = []
        for limit in (1000, 0):
            monkeypatch.setattr(timeline, "SPLIT_EDGES", limit)
            monkeypatch.setattr(timeline, "CHUNK_CELLS", 40 if limit == 0 else 4_000_000)
            got.append(sorted(run_timeline(deltas, x, [LOW, HIGH], 1e-6, 2, strategy, emit, local=True).representations.collect()))
        assert got[0] == got[1] and got[0]
        assert len({(r["step"], r["node"]) for r in got[0]}) == len(got[0])


def test_changes_of_a_step_move_no_other_edges():
    """places are made for several steps at once; an edge that has none yet gets one on the way."""
    g = LocalGraph(np.arange(4), np.ones((4, 2)), [FilterSpec.restart(0.2)])
    g.expect(np.array([0, 1, 1, 2]), np.array([1, 0, 2, 1]))
    keys = g.keys
    assert g.weight == {} and g.counts.tolist() == [0, 0, 0, 0]
    g.apply(np.array([0, 1]), np.array([1, 0]), np.ones(2))
    g.reset()
    g.push(1e-9)
    g.apply(np.array([1, 2, 0, 1]), np.array([2, 1, 1, 0]), np.array([2.0, 2.0, -1.0, -1.0]))
    assert g.keys is keys and g.weight == {(1, 2): 2.0, (2, 1): 2.0} and g.counts.tolist() == [0, 1, 1, 0]
    g.apply(np.array([3, 0]), np.array([0, 3]), np.ones(2))
    g.push(1e-9, apart=True)
    assert g.weight == {(0, 3): 1.0, (1, 2): 2.0, (2, 1): 2.0, (3, 0): 1.0} and g.read() == pytest.approx(g.exact(), abs=1e-7)


@pytest.mark.parametrize("specs", [[LOW], [LOW, HIGH]])
def test_columns_of_one_task_share_its_graph(monkeypatch, specs):
    """a task builds the graph once for its columns of a filter, and all cells are dealt once."""
    monkeypatch.setattr(timeline, "SPLIT_EDGES", 0)
    tasks, apart = timeline._columns_of_tasks(specs, 50, "incremental", 1)
    assert apart and len(tasks) == 8 and sum(map(len, tasks)) <= 8 + len(specs) - 1
    cells = [(s, c) for task in tasks for numbers, a, b in task for s in numbers for c in range(a, b)]
    assert sorted(cells) == [(s, c) for s in range(len(specs)) for c in range(50)]


def test_larger_graphs_stay_on_arrays_in_fewer_tasks():
    """twelve million changes run on arrays; the more edges each task holds, the fewer tasks share the columns."""
    specs = [FilterSpec.restart(0.2), FilterSpec.alternating(0.2)]
    assert timeline.LOCAL_EDGES >= 12_000_000
    for n, tasks in ((300_000, 8), (10_000_000, 8), (12_000_000, 6), (20_000_000, 4)):
        columns, apart = timeline._columns_of_tasks(specs, 8, "incremental", n)
        assert len(columns) == tasks and apart
        assert sorted((s, c) for parts in columns for numbers, a, b in parts for s in numbers for c in range(a, b)) == [(s, c) for s in range(2) for c in range(8)]
