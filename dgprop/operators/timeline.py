"""Representations for every step of a changing graph.

``incremental`` repairs the state after each step and pushes on; ``recompute``
starts anew at each step; ``per_event`` makes a step of each edge change; ``auto``
repairs, and starts anew where the repaired state has a greater potential than a
cold start.  Features of any width are run in blocks of columns.  Graphs up to
``LOCAL_EDGES`` half-edges and changes run on arrays, columns dealt to tasks, larger
ones as DataFrame rounds; both give the same rows up to rounding, and the same counts.
``per_event`` is meant for a few hundred changes: each is a run of its own.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dgprop.operators.filters import FilterSpec
from dgprop.operators.graph import affected, apply_deltas
from dgprop.operators.kernel import LocalGraph
from dgprop.operators.propagate import BLOCK, PushResult, cells, init_state, push
from dgprop.operators.update import repair
from dgprop.plans.lineage import cut, ensure_checkpoint_dir, stored

LOCAL_EDGES = 20_000_000
#: Half-edges and changes beyond which columns are dealt to several tasks, how many these are and what all of them hold at most, and cells of a node range that are put together at once.
SPLIT_EDGES, MOST_TASKS, HELD_EDGES, CHUNK_CELLS = 200_000, 8, 80_000_000, 4_000_000
STATS = "step int, rounds int, pushes bigint, edges_touched bigint, affected_nodes bigint, deltas bigint, max_abs_q double, potential double, emitted bigint"


@dataclass
class TimelineResult:
    """Rows (step, node, z), and the counts of each step."""

    representations: DataFrame
    stats: DataFrame


def blocks_of(specs: list[FilterSpec], dim: int) -> list[tuple[int, int]]:
    """Ranges of feature columns that one loop carries, all filters of a column together."""
    each = max(1, 2 * BLOCK // max(1, len(specs)))
    return [(a, min(dim, a + each)) for a in range(0, dim, each)]


def _joined(parts: list[dict]) -> dict:
    """Counts of one step from those of its blocks: the most rounds, and sums."""
    return {
        "rounds": max(p["rounds"] for p in parts),
        **{k: sum(p[k] for p in parts) for k in ("pushes", "edges_touched", "potential")},
        "max_abs_q": max(p["max_abs_q"] for p in parts),
    }


@dataclass
class _Inputs:
    """Deltas and features of a timeline as arrays, by node numbers in the order of nodes."""

    nodes: np.ndarray
    x: np.ndarray
    #: step, from where in the arrays, to where.
    turns: list[tuple[int, int, int]]
    src: np.ndarray
    dst: np.ndarray
    dw: np.ndarray


def _unpacked(batches: Iterator[pa.RecordBatch], dim: int) -> dict[int, _Inputs]:
    """By task its inputs, from packed rows."""
    held: dict[int, tuple[list, list]] = {}
    for batch in batches:
        for task, deltas, features in zip(batch.column("task").to_pylist(), batch.column("deltas"), batch.column("features"), strict=True):
            for blob, into in zip((deltas, features), held.setdefault(task, ([], [])), strict=True):
                if blob.is_valid:
                    into.append(pa.ipc.open_stream(blob.as_buffer()).read_all())
    return {task: _inputs(*parts, dim) for task, parts in held.items()}


def _order(step: np.ndarray, src: np.ndarray, dst: np.ndarray, n: int) -> np.ndarray:
    """Places in the order of step, source and target, by one number for all three where it has room for them."""
    low = int(step.min(initial=0))
    if (int(step.max(initial=0)) - low + 1) * n * n >= 1 << 62:
        return np.lexsort((dst, src, step))
    return np.argsort(((step.astype(np.int64) - low) * n + src) * n + dst, kind="stable")


def _inputs(deltas: list[pa.Table], features: list[pa.Table], dim: int) -> _Inputs:
    column = lambda parts, name, kind: np.concatenate([p.column(name).to_numpy() for p in parts]) if parts else np.zeros(0, kind)
    node = column(features, "node", np.int64)
    x = [np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in p.column("x").chunks] or [np.zeros(0)]).astype(float).reshape(p.num_rows, dim) for p in features]
    order = np.argsort(node)
    nodes = node[order]
    step = column(deltas, "step", np.int32)
    src, dst = (np.searchsorted(nodes, column(deltas, end, np.int64)).astype(np.int32) for end in ("src", "dst"))
    by = _order(step, src, dst, len(nodes))
    step = step[by]
    starts = np.flatnonzero(np.diff(step, prepend=step[:1] - 1)) if len(step) else np.zeros(0, int)
    turns = [(int(step[a]), int(a), int(b)) for a, b in zip(starts, [*starts[1:], len(step)], strict=True)]
    return _Inputs(nodes, (np.concatenate(x) if x else np.zeros((0, dim)))[order], turns, src[by], dst[by], column(deltas, "dw", float)[by])


def _states(of: _Inputs, specs: list[FilterSpec], a: int, b: int, rmax: float, strategy: str, apart: bool = False) -> Iterator[tuple[int, int, LocalGraph, dict]]:
    """Step, number of deltas, graph and counts of columns a to b after each step with changes; ``apart`` pushes column by column."""
    g, known = LocalGraph(np.arange(len(of.nodes)), of.x[:, a:b], specs), 0
    for turn, (step, low, high) in enumerate(of.turns):
        if high > known:
            # Places for the changes of some steps at once: moving all edges for them is rare, and few places are empty.
            most = low + len(g.keys) // 4
            known = max([high, *(end for *_, end in of.turns[turn:] if end <= most)])
            g.expect(of.src[low:known], of.dst[low:known])
        src, dst, dw = of.src[low:high], of.dst[low:high], of.dw[low:high]
        groups = [slice(None)]
        if strategy == "per_event":
            _, inverse = np.unique(np.stack((np.minimum(src, dst), np.maximum(src, dst)), 1), axis=0, return_inverse=True)
            groups = [np.flatnonzero(inverse.ravel() == k) for k in range(inverse.max() + 1)]
        hit, totals = 0, {"rounds": 0, "pushes": 0, "edges_touched": 0}
        for k, at in enumerate(groups):
            hit += g.apply(src[at], dst[at], dw[at])
            if strategy == "recompute" or (turn == 0 and k == 0):
                g.reset()
            elif strategy == "auto":
                y, q, repaired = g.y.copy(), g.q.copy(), g.potential()
                g.reset()
                if repaired <= g.potential():
                    g.y, g.q = y, q
            done = g.push(rmax, apart=apart)
            for name in totals:
                totals[name] += done[name]
        yield step, high - low, g, totals | {"max_abs_q": done["max_abs_q"], "potential": g.potential(), "affected_nodes": hit}


def _columns_of_tasks(specs: list[FilterSpec], dim: int, strategy: str, n: int) -> tuple[list[list[tuple[list[int], int, int]]], bool]:
    """Filters and column ranges that each task runs, and whether columns are pushed apart. Cells of different columns and filters never
    meet, but for ``auto``, which decides for all that one loop carries; so on larger graphs columns are dealt to the tasks, where those of one filter share the graph."""
    loops = [(list(range(len(specs))), a, b) for a, b in blocks_of(specs, dim)]
    if n <= SPLIT_EDGES:
        return [loops], False
    if strategy == "auto":
        return [[loop] for loop in loops], False
    total, out = len(specs) * dim, []
    tasks = max(1, min(MOST_TASKS, total, HELD_EDGES // n))
    for i in range(tasks):
        low, high = i * total // tasks, (i + 1) * total // tasks
        out.append([([s], max(low - s * dim, 0), min(high - s * dim, dim)) for s in range(len(specs)) if low < (s + 1) * dim and high > s * dim])
    return out, True


def _packed(df: DataFrame, columns: tuple[str, ...]) -> DataFrame:
    """Batches of rows as one binary value each, with the number of rows."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, batch.schema) as out:
                out.write_batch(batch)
            yield pa.RecordBatch.from_pydict({"n": pa.array([batch.num_rows], pa.int64()), "blob": pa.array([sink.getvalue().to_pybytes()], pa.binary())})

    return df.select(*columns).mapInArrow(work, "n bigint, blob binary")


def pack(deltas: DataFrame, features: DataFrame) -> DataFrame:
    """What runs on arrays read."""
    changes = _packed(deltas, ("step", "src", "dst", "dw")).select("n", F.col("blob").alias("deltas"), F.lit(None).cast("binary").alias("features"))
    return stored(changes.unionByName(_packed(features, ("node", "x")).select("n", F.lit(None).cast("binary").alias("deltas"), F.col("blob").alias("features"))))


def _to_tasks(packed: DataFrame, tasks: int) -> DataFrame:
    """All packed rows in each task."""
    return packed.select(F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task"), "deltas", "features").repartitionById(tasks, F.col("task"))


def _local(packed: DataFrame, n: int, specs: list[FilterSpec], rmax: float, dim: int, strategy: str, emit: str) -> TimelineResult:
    columns, apart = _columns_of_tasks(specs, dim, strategy, n)
    width = len(specs) * dim
    row = pa.schema([("chunk", pa.int32()), ("step", pa.int32()), ("place", pa.list_(pa.int32())), ("nodes", pa.binary()), ("z", pa.binary())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for task, of in _unpacked(batches, dim).items():
            size = max(1, CHUNK_CELLS // max(1, width * len(of.turns)))
            for k, (numbers, a, b) in enumerate(columns[task]):
                place = [s * dim + c for s in numbers for c in range(a, b)]
                for i, (step, _, g, _) in enumerate(_states(of, [specs[s] for s in numbers], a, b, rmax, strategy, apart)):
                    if emit == "last" and i + 1 < len(of.turns):
                        continue
                    z = g.read()
                    for chunk, low in enumerate(range(0, len(z), size)):
                        nodes = of.nodes[low : low + size].tobytes() if task == k == 0 else None
                        yield pa.RecordBatch.from_pydict({"chunk": [chunk], "step": [step], "place": [place], "nodes": [nodes], "z": [np.ascontiguousarray(z[low : low + size]).tobytes()]}, row)

    def rows(of: pa.Table) -> pa.Table:
        nodes, steps = {}, {}
        for r in of.to_pylist():
            if r["nodes"] is not None:
                nodes[r["step"]] = np.frombuffer(r["nodes"], np.int64)
            steps.setdefault(r["step"], []).append((r["place"], r["z"]))
        made, last = [], None
        for step in sorted(steps):
            z = np.empty((len(nodes[step]), width))
            for place, values in steps[step]:
                z[:, place] = np.frombuffer(values).reshape(len(z), len(place))
            keep = np.ones(len(z), bool) if emit != "changed" or last is None else (z != last).any(axis=1)
            last, kept = z, z[keep]
            lists = pa.ListArray.from_arrays(np.arange(0, kept.size + 1, max(1, width), dtype=np.int32), kept.ravel()) if width else pa.array([[]] * len(kept), pa.list_(pa.float64()))
            made.append(pa.table({"step": np.full(len(kept), step, np.int32), "node": nodes[step][keep], "z": lists}))
        return pa.concat_tables(made)

    def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for of in _unpacked(batches, dim).values():
            last = None
            for now in zip(*[_states(of, specs, a, b, rmax, strategy) for a, b in blocks_of(specs, dim)], strict=True):
                z = np.concatenate([g.read() for _, _, g, _ in now], axis=1)
                emitted = len(z) if emit != "changed" or last is None else int((z != last).any(axis=1).sum())
                last = z
                made = {"step": now[0][0]} | _joined([p for *_, p in now]) | {"affected_nodes": now[-1][3]["affected_nodes"], "deltas": now[0][1], "emitted": emitted}
                yield pa.RecordBatch.from_pandas(pd.DataFrame([made])[[c.split()[0] for c in STATS.split(", ")]].astype({"step": np.int32, "rounds": np.int32}), preserve_index=False)

    parts = _to_tasks(packed, len(columns)).mapInArrow(work, "chunk int, step int, place array<int>, nodes binary, z binary")
    return TimelineResult(parts.groupBy("chunk").applyInArrow(rows, "step int, node bigint, z array<double>"), _to_tasks(packed, 1).mapInArrow(counts, STATS))


def potential(state: DataFrame, specs: list[FilterSpec], dim: int) -> float:
    """The sum of the residuals' sizes times the degree, which bounds the work that is left."""
    sizes = [F.abs(F.col(q)) for q in cells("q", specs, dim)]
    return state.agg(F.coalesce(F.sum(sum(sizes[1:], sizes[0]) * F.col("D")), F.lit(0.0))).head()[0]


def _distributed(deltas: DataFrame, features: DataFrame, specs: list[FilterSpec], rmax: float, dim: int, strategy: str, emit: str) -> TimelineResult:
    spark = deltas.sparkSession
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/timeline-{uuid.uuid4().hex}"
    deltas = one_edge_steps(deltas) if strategy == "per_event" else deltas.select("step", F.lit(0).alias("part"), "src", "dst", "dw")
    deltas.write.partitionBy("step", "part").parquet(f"{folder}/deltas")
    deltas = spark.read.schema("src bigint, dst bigint, dw double, step int, part int").parquet(f"{folder}/deltas")
    # As many rows as there are steps, or changed edges where each is a step.
    turns = [(r["step"], r["part"]) for r in deltas.select("step", "part").distinct().orderBy("step", "part").collect()]
    ranges = blocks_of(specs, dim)
    xs = [cut(features.select("node", F.slice("x", a + 1, b - a).alias("x"))) for a, b in ranges]
    edges, states, before = spark.createDataFrame([], "src bigint, dst bigint, w double"), [None] * len(ranges), None
    stats: dict[int, list[list[dict]]] = {}
    counts: dict[int, list[int]] = {}
    for k, (step, part) in enumerate(turns):
        now = deltas.filter((F.col("step") == step) & (F.col("part") == part)).select("src", "dst", "dw")
        after = cut(apply_deltas(edges, now))
        hit = counts.setdefault(step, [0, 0, 0])
        hit[0] += affected(now).count()
        hit[1] += now.count()
        rounds = []
        for i, (a, b) in enumerate(ranges):
            cold = init_state(xs[i], after, specs, b - a)
            start = cold
            if states[i] is not None and strategy != "recompute":
                start = repair(states[i], now, edges, xs[i], specs, b - a)
                if strategy == "auto" and potential(start, specs, b - a) > potential(cold, specs, b - a):
                    start = cold
            done = push(after, start, specs, rmax, b - a)
            states[i] = done.state
            end = done.stats[-1]
            rounds.append({"rounds": end["round"], "pushes": sum(r["active_cells"] for r in done.stats), "edges_touched": sum(r["edges_touched"] for r in done.stats), "max_abs_q": float(end["max_abs_q"]), "potential": float(end["phi"])})
        stats.setdefault(step, []).append(rounds)
        edges = after
        if k + 1 < len(turns) and turns[k + 1][0] == step:
            continue
        z = _side_by_side(states, specs, ranges)
        if emit == "changed":
            z = cut(z)
        rows = z
        if emit == "changed" and before is not None:
            rows = z.join(before.withColumnRenamed("z", "old"), "node", "left").filter("old IS NULL OR z <> old").select("node", "z")
        before = z
        if emit != "last" or k + 1 == len(turns):
            rows.write.parquet(f"{folder}/rows/step={step}")
            hit[2] = spark.read.parquet(f"{folder}/rows/step={step}").count()
        else:
            hit[2] = rows.count()
    made = []
    for step, parts in stats.items():
        each = [[p[i] for p in parts] for i in range(len(ranges))]
        blocks = [{"rounds": sum(p["rounds"] for p in e), "pushes": sum(p["pushes"] for p in e), "edges_touched": sum(p["edges_touched"] for p in e), "max_abs_q": e[-1]["max_abs_q"], "potential": e[-1]["potential"]} for e in each]
        j = _joined(blocks)
        made.append((step, j["rounds"], j["pushes"], j["edges_touched"], counts[step][0], counts[step][1], j["max_abs_q"], j["potential"], counts[step][2]))
    schema = "node bigint, z array<double>, step int"
    out = spark.read.schema(schema).parquet(f"{folder}/rows") if turns else spark.createDataFrame([], schema)
    return TimelineResult(out.select("step", "node", "z"), spark.createDataFrame(made, STATS))


def _side_by_side(states: list[DataFrame], specs: list[FilterSpec], ranges: list[tuple[int, int]]) -> DataFrame:
    """node and z from the states of all blocks: all columns of the first filter, then of the next."""
    out = None
    for i, (state, (a, b)) in enumerate(zip(states, ranges, strict=True)):
        part = PushResult(state, specs, b - a).both_bands().withColumnRenamed("z", f"z{i}")
        out = part if out is None else out.join(part, "node")
    pieces = [F.slice(f"z{i}", s * (b - a) + 1, b - a) for s in range(len(specs)) for i, (a, b) in enumerate(ranges)]
    return out.select("node", F.concat(*pieces).alias("z"))


def run_timeline(deltas: DataFrame, features: DataFrame, specs: list[FilterSpec], rmax: float, dim: int, strategy: str = "incremental", emit: str = "all", local: bool | None = None, packed: DataFrame | None = None) -> TimelineResult:
    """``deltas`` has both directions of every change; ``emit`` is all, changed or last; ``packed`` is what ``pack`` makes of both, for several runs."""
    if strategy not in ("incremental", "recompute", "per_event", "auto"):
        raise ValueError(strategy)
    if local is not False:
        packed = pack(deltas, features) if packed is None else packed
        n, rest = packed.agg(*[F.coalesce(F.sum(F.when(F.col(c).isNotNull(), F.col("n"))), F.lit(0)) for c in ("deltas", "features")]).head()
        if local or n + rest * len(specs) <= LOCAL_EDGES:
            return _local(packed, n, specs, rmax, dim, strategy, emit)
    return _distributed(deltas, features, specs, rmax, dim, strategy, emit)


def one_edge_steps(deltas: DataFrame) -> DataFrame:
    """step, part, src, dst, dw: a part of its step for each changed edge, in the order of ends."""
    low, high = F.least("src", "dst"), F.greatest("src", "dst")
    inside = F.dense_rank().over(Window.partitionBy("step").orderBy(low, high)) - 1
    return deltas.select("step", inside.cast("int").alias("part"), "src", "dst", "dw")


def save_state(state: DataFrame, path: str, version: int) -> None:
    state.write.mode("overwrite").parquet(f"{path}/version={version}")


def load_state(spark: SparkSession, path: str, version: int) -> DataFrame:
    return spark.read.parquet(f"{path}/version={version}")


def state_columns(specs: list[FilterSpec], dim: int) -> list[str]:
    return ["node", "D", *cells("y", specs, dim), *cells("q", specs, dim)]
