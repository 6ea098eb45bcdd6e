"""Gradients, measures and splits."""

import hashlib
import math
import pickle

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from dgprop.baselines import aggregates
from dgprop.baselines.neural import causal_walk_features, snapshot_attention
from dgprop.models import networks
from dgprop.models.networks import ENCODERS, ClassModel, LinkModel, fit_partitions, fit_rows, gradient
from dgprop.operators import metrics as M
from dgprop.operators import sequences
from dgprop.operators.filters import FilterSpec, restart_truncated, weighted_hops
from dgprop.plans.lineage import at_once
from dgprop.tasks import link, splits
from dgprop.workloads import learning


def batch(rng):
    return pd.DataFrame({"xa": [rng.normal(size=(5, 3)).tolist() for _ in range(6)], "xb": [rng.normal(size=(5, 3)).tolist() for _ in range(6)], "ma": [[0, 0, 1, 1, 1]] * 6, "mb": [[0, 1, 1, 1, 1]] * 6, "label": [0, 1, 1, 0, 1, 0]})


@pytest.mark.parametrize("kind", ENCODERS)
@pytest.mark.parametrize("how", ["concat", "hadamard", "average", "difference"])
def test_gradients_and_fit(kind, how):
    rng = np.random.default_rng(0)
    model, rows = LinkModel(kind, 3, 4, how), batch(rng)
    p = model.init(1)
    _, g = gradient(model, p, rows)
    for name in p:
        i = p[name].size // 2
        values = []
        for e in (1e-6, -1e-6):
            moved = p[name].copy().ravel()
            moved[i] += e
            values.append(gradient(model, p | {name: moved.reshape(p[name].shape)}, rows)[0])
        assert (values[0] - values[1]) / 2e-6 == pytest.approx(g[name].ravel()[i], abs=1e-5)
    fitted = fit_rows(model, rows, 250, 6, 0.05, 0)
    assert gradient(model, fitted, rows)[0] < 0.5 * gradient(model, p, rows)[0]


def test_gradients_from_partitions_equal_those_of_one(spark):
    rows = pd.DataFrame({"x": [[float(i), 1.0] for i in range(8)], "label": [int(i > 3) for i in range(8)]})
    model = ClassModel([2, 3, 2])
    spread = fit_partitions(model, spark.createDataFrame(rows).repartition(3), 5, 0.05, 0)
    whole = fit_rows(model, rows, 5, 8, 0.05, 0)
    for k in whole:
        assert spread[k] == pytest.approx(whole[k], abs=1e-9)


def test_measures_with_ties(spark):
    rows = spark.createDataFrame([(1, 0.9, 1), (2, 0.8, 0), (3, 0.8, 1), (4, 0.1, 0)], "id int, score double, label int")
    assert M.average_precision(rows).head()[0] == pytest.approx(0.5 * 1 + 0.5 * 2 / 3)
    assert M.roc_auc(rows).head()[0] == pytest.approx(3.5 / 4)
    one = rows.filter("label = 1")
    assert M.average_precision(one).head()[0] == pytest.approx(1.0)
    assert M.roc_auc(one).head()[0] is None
    ranked = spark.createDataFrame([(1, 1, 0.5, 1), (1, 1, 0.7, 0), (1, 1, 0.5, 0), (2, 1, 0.9, 1), (2, 1, 0.1, 0)], "query_id bigint, step int, score double, label int")
    for ties, rank in (("mean", 2.5), ("optimistic", 2), ("pessimistic", 3)):
        assert M.mrr(ranked, ties).head()[0] == pytest.approx((1 / rank + 1) / 2)
    classes = spark.createDataFrame([(0, 0), (0, 1), (1, 1), (2, 1)], "label int, predicted int")
    f = M.f1(classes).head()
    assert f["f1_micro"] == pytest.approx(0.5)
    assert M.relative_gain(0.3110, 0.2203) == pytest.approx(0.41, abs=0.01)


def test_splits_do_not_leak(spark):
    pairs = spark.createDataFrame([(i, i // 10, i % 7, i % 5) for i in range(100)], "query_id bigint, step int, src bigint, dst bigint")
    parts = splits.time_split(pairs).toPandas()
    assert parts[parts.part == "train"].step.max() < parts[parts.part == "valid"].step.min() <= parts[parts.part == "test"].step.min()
    pool = splits.indexed(pairs.selectExpr("dst + 100 AS node").distinct())
    assert sorted(r["idx"] for r in pool.collect()) == list(range(5))
    no = splits.negatives(pairs, splits.indexed(pairs.selectExpr("dst AS node").distinct()), 2, 1).toPandas()
    known = set(zip(pairs.toPandas().src, pairs.toPandas().dst, strict=True))
    assert not known & set(zip(no.src, no.dst, strict=True))


def test_negatives_are_all_there_and_even(spark):
    """However many targets a source knows, it gets as many draws as asked for, of the free ones alike."""
    known = spark.createDataFrame([(1, d) for d in range(90)] + [(2, d) for d in range(100)] + [(3, 7)], "src bigint, dst bigint")
    pool = splits.indexed(spark.range(100).selectExpr("id AS node"))
    pairs = spark.createDataFrame([(i, 5, 1 + i % 3, 0) for i in range(300)], "query_id bigint, step int, src bigint, dst bigint")
    no = splits.negatives(pairs, pool, 4, 1, known).toPandas()
    assert (no.groupby("query_id").size() == 4).all() and set(no.src) == {1, 3}
    assert set(no[no.src == 1].dst) == set(range(90, 100)) and 7 not in set(no[no.src == 3].dst)
    assert set(no[no.src == 1].n_free) == {10} and no[no.src == 1].groupby("dst").size().min() > 15
    every = splits.negatives(pairs.limit(2), pool, 1000, 1, known).toPandas()
    assert all(set(g.dst) == set(range(90, 100)) and len(g) == 10 for _, g in every[every.src == 1].groupby("query_id"))


def test_fit_on_a_bounded_sample(spark):
    from dgprop.tasks.fitting import fitted

    rows = spark.createDataFrame([(i, float(i)) for i in range(100)], "id bigint, v double")
    assert fitted(rows, ["id"], lambda p: (len(p), p.id.is_monotonic_increasing), 10) == (10, True)
    assert fitted(rows, ["id"], lambda p: p.v.sum()) == 4950
    assert fitted(rows.limit(0), ["id"], len) is None


def test_filters():
    for spec in (FilterSpec.restart(0.2), FilterSpec.alternating(0.2), FilterSpec.power(0.5), FilterSpec.neg_power(0.5)):
        assert sum(abs(g) for g in spec.gammas(200)) == pytest.approx(spec.mass)
        assert sum(g * 0.5**k for k, g in enumerate(spec.gammas(200))) == pytest.approx(spec.response(0.5))
    assert FilterSpec.restart(0.2).mass == FilterSpec.alternating(0.2).mass == pytest.approx(1)
    assert sum(restart_truncated(5, 0.3)) == pytest.approx(1)
    assert weighted_hops([1, -3]) == [0.25, -0.75]


def test_walks_back_in_time_see_only_what_was_before():
    events = pd.DataFrame({"src": [1, 1, 3], "dst": [11, 12, 11], "ts_us": [10, 20, 15]})
    pairs = pd.DataFrame({"src": [1, 1, 9], "dst": [11, 12, 11], "ts_us": [5, 16, 99]})
    for pool in ("mean", "attn"):
        x = causal_walk_features(pairs, events, 4, 1, pool)
        assert x.shape == (3, 8)
        # Before 5 nothing had happened: both paths are their starts only, each in its own set.
        assert np.allclose(x[0], [0.5, 0, 0.5, 0, 0, 0, 0, 0])
    # Before 16 node 1 had met 11 only, 12 nobody: place 0 is in its own set, place 1 of the first path too.
    assert np.allclose(causal_walk_features(pairs, events, 4, 1)[1], [0.5, 0, 0.5, 0, 0, 0.5, 0, 0])
    assert causal_walk_features(pairs[:0], events, 4, 1).shape == (0, 8)


def test_walks_back_in_time_are_scored(spark, sf):
    got = {r["pool"]: r["average_precision"] for r in learning.lp_causal_walks(spark, sf).collect()}
    assert set(got) == {"mean", "attn"} and all(0 < v <= 1 for v in got.values())


@pytest.mark.parametrize("least", [20.0, 0.02])
def test_walks_from_few_draws_are_those_of_all(spark, monkeypatch, least):
    # Blocks and multiples so small that hubs are divided and that the draws have to be looked at again.
    monkeypatch.setattr(aggregates, "BLOCK_EDGES", 8)
    monkeypatch.setattr(aggregates, "LEAST", least)
    digest = lambda *p: int(hashlib.md5(":".join(map(str, p)).encode()).hexdigest()[:8], 16)
    edges = [(i, 100 + i % 2, 1.0 + i % 3) for i in range(60)] + [(0, 101, 2.0)]
    edges = edges + [(b, a, w) for a, b, w in edges]
    by: dict[int, dict[int, float]] = {}
    for a, b, w in edges:
        by.setdefault(a, {})[b] = w
    df = spark.createDataFrame(edges, "src bigint, dst bigint, w double")
    starts = df.select(F.col("src").alias("node")).distinct()
    for p, q in ((1.0, 1.0), (0.5, 2.0)):
        want = set()
        for start in by:
            node, prev = start, None
            want.add((start, 0, 0, node))
            for pos in (1, 2, 3):
                weight = {b: w if prev is None else w / p if b == prev else w if b in by[prev] else w / q for b, w in by[node].items()}
                node, prev = min((-math.log((digest(4, start, 0, pos, b) + 1) / 4294967297.0) / w, b) for b, w in weight.items())[1], node
                want.add((start, 0, pos, node))
        assert {tuple(r) for r in aggregates.walks(df, starts, 3, 1, 4, p, q).collect()} == want
    timed = spark.createDataFrame([(a, b, 7 * a + b) for a, b, _ in edges], "src bigint, dst bigint, ts_us bigint")
    want = set()
    for start in by:
        node, at = start, -1
        want.add((start, 0, node, at))
        for pos in (1, 2):
            later = [(digest(6, start, pos, b, 7 * node + b), b, 7 * node + b) for b in by[node] if 7 * node + b > at]
            if not later:
                break
            _, node, at = min(later)
            want.add((start, pos, node, at))
    assert {tuple(r) for r in aggregates.temporal_walks(timed, starts, 2, 6).collect()} == want


def test_attention_over_snapshots_of_many_nodes():
    rng = np.random.default_rng(2)
    few = pd.DataFrame({"node": np.arange(6), "x": list(rng.normal(size=(6, 4)))})
    deltas = pd.DataFrame({"step": [0, 0, 1, 1, 2, 2], "src": [0, 1, 1, 2, 0, 1], "dst": [1, 0, 2, 1, 1, 0], "dw": [1.0, 1, 1, 1, -1, -1]})
    got = snapshot_attention(3)(deltas, few)
    # Dense, at each step; then over the steps so far.
    draw = np.random.default_rng(0)
    y = np.stack(few["x"]) @ draw.normal(0, 0.5, (4, 3))
    a, b = draw.normal(size=3), draw.normal(size=3)
    adj, past = np.zeros((6, 6)), []
    for step, rows in deltas.groupby("step"):
        np.add.at(adj, (rows["src"], rows["dst"]), rows["dw"])
        score = (y @ a)[:, None] + (y @ b)[None, :]
        e = np.where((adj > 1e-12) | np.eye(6, dtype=bool), np.exp(np.where(score > 0, score, 0.2 * score)), 0)
        past.append(e / e.sum(1, keepdims=True) @ y)
        s = np.stack(past, axis=1)
        t = np.exp(np.einsum("nh,nth->nt", s[:, -1], s) / np.sqrt(3))
        assert np.allclose(np.stack(got[got["step"] == step]["z"]), np.einsum("nt,nth->nh", t / t.sum(1, keepdims=True), s))
    # A square array of these nodes would take 720 GB.
    many = pd.DataFrame({"node": np.arange(300_000), "x": list(rng.normal(size=(300_000, 4)))})
    assert len(snapshot_attention(3)(deltas, many)) == 900_000


def test_models_share_sequences_of_the_asked_ends(spark):
    """Only ends that pairs ask for get sequences, and two models are fitted on the same rows as one alone."""
    z = spark.createDataFrame([(s, n, [float((n * s) % 5), float(n % 2)]) for s in range(5) for n in range(20)], "step int, node bigint, z array<double>")
    rows = [(i, 2 + i % 3, i % 4, 10 + i % 5, i % 2, "train" if i % 3 < 2 else "test") for i in range(24)]
    pairs = spark.createDataFrame(rows, "query_id bigint, step int, src bigint, dst bigint, label int, part string")
    task = link.prepare(z, pairs, 3, 2)
    asked = {(r[1] - 1, n) for r in rows for n in (r[2], r[3])}
    assert {(r["step"], r["node"]) for r in task.sequences.collect()} == asked
    model = LinkModel("lstm", 2, 4)
    both = at_once(lambda seed: sorted(task.run(model, 2, seed=seed).collect()), [0, 1])
    assert both[0] == sorted(link.run(z, pairs, 3, model, 2, seed=0).collect()) and both[0] != both[1]
    assert task.run(model, 1).count() == sum(r[5] == "test" for r in rows)


def test_negatives_search_known_targets_by_halves(spark):
    """No draw walks through all that its source knows."""
    pairs = spark.createDataFrame([(i, 0, i % 2, i) for i in range(10)], "query_id bigint, step int, src bigint, dst bigint")
    no = splits.negatives(pairs, splits.indexed(spark.range(40).selectExpr("id AS node")), 3, 1)
    plan = no._jdf.queryExecution().optimizedPlan().toString()
    assert "filter(taken" not in plan and no.count() == 30


def test_ranks_take_one_pass_over_the_scores(spark):
    """Scores are worked out once; a query without others ranks first, one without a positive not at all."""
    rows = spark.createDataFrame([(1, 1, 0.5, 1), (1, 1, 0.7, 0), (2, 1, 0.1, 1), (3, 1, 0.9, 0)], "query_id bigint, step int, score double, label int")
    ranks = M.reciprocal_ranks(rows)
    assert {(r["query_id"], r["rr"]) for r in ranks.collect()} == {(1, 0.5), (2, 1.0)}
    assert "Join" not in ranks._jdf.queryExecution().optimizedPlan().toString()


def test_sequences_of_asked_ends_are_not_moved_again(spark):
    """asked rows are marked before the windows; a join after them shuffled the sequences of all nodes. A node has rows of some steps only."""
    z = spark.createDataFrame([(s, n, [float((n * s) % 5), float(n)]) for s in range(6) for n in range(8) if (s + n) % 4], "step int, node bigint, z array<double>")
    ends = spark.createDataFrame([(3, 1), (4, 2), (2, 2), (1, 3), (5, 99)], "step int, node bigint")
    got = link.padded(sequences.deltas(sequences.with_asked(z, ends), "diff", "asked"), 3, 2, "asked")
    want = link.padded(sequences.deltas(z), 3, 2).join(ends, ["step", "node"], "left_semi")
    assert sorted(got.collect()) == sorted(want.select("step", "node", "x", "m").collect()) and got.count() > 0
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()
    earlier = sequences.with_earlier(z)
    assert sorted(earlier.collect()) == sorted(sequences.deltas(z).select("step", "node").collect())


def test_trades_and_representations_are_joined_once(spark, sf, monkeypatch):
    """the rows that are counted, fitted and scored are read, not joined anew."""
    seen = []
    monkeypatch.setattr(learning.node, "run", lambda rows, *_: seen.append(rows) or rows.select("label", "part", F.lit(0.5).alias("score")))
    learning.nc_returns(spark, sf)
    assert "lineitem" not in str(seen[0].inputFiles())


def test_models_are_fitted_on_all_rows(spark, monkeypatch):
    """F18-F28: no training row is left out; parts go side by side and are averaged by rows after each epoch, and one part is the fit in one process."""
    from dgprop.models.networks import fit_dealt
    from dgprop.tasks import fitting, node

    rng = np.random.default_rng(4)
    rows = pd.DataFrame({"id": range(90), "x": rng.normal(size=(90, 2)).tolist(), "label": [i % 2 for i in range(90)], "part": ["test" if i % 9 == 0 else "train" for i in range(90)]})
    df, train = spark.createDataFrame(rows), rows[rows.part == "train"].reset_index(drop=True)
    model = ClassModel([2, 3, 2])
    one = fitting.dealt(df.filter("part = 'train'"), ["id"], model.arrays, 80)
    assert [r["n"] for r in one.collect()] == [80]
    whole = fit_rows(model, train, 3, 16, 0.05, 0)
    assert all(np.array_equal(v, whole[k]) for k, v in fit_dealt(model, one, 3, 16, 0.05, 0).items())
    monkeypatch.setattr(fitting, "PART_ROWS", 20)
    made = []
    real = fitting.dealt
    monkeypatch.setattr(node, "dealt", lambda *a: made.append(real(*a)) or made[-1])
    assert node.run(df, model, 2).count() == 10
    held = made[0].collect()
    assert sum(r["n"] for r in held) == 80 and 1 < len(held) <= 4
    # One epoch: the mean of what the parts come to alone.
    several = fit_dealt(model, made[0], 1, 16, 0.05, 0)
    alone = []
    for r in held:
        arrays, p = pickle.loads(r["arrays"]), model.init(0)
        networks._epoch(model, p, networks.Adam(p, 0.05), arrays, np.random.default_rng([0, r["deal"]] if r["deal"] else 0).permutation(r["n"]), 16)
        alone.append({k: v * (r["n"] / 80) for k, v in p.items()})
    assert all(several[k] == pytest.approx(sum(p[k] for p in alone)) for k in several)
    z = spark.createDataFrame([(s, n, [float((n * s) % 5), float(n % 2)]) for s in range(5) for n in range(20)], "step int, node bigint, z array<double>")
    pairs = spark.createDataFrame([(i, 2 + i % 3, i % 4, 10 + i % 5, i % 2, "train") for i in range(60)], "query_id bigint, step int, src bigint, dst bigint, label int, part string")
    task = link.prepare(z, pairs, 3, 2)
    assert task.parts.count() > 1 and task.parts.agg(F.sum("n")).head()[0] == 60
    x = [v for r in task.parts.collect() for c in ("xa", "xb") for v in pickle.loads(r["arrays"])[c].ravel()]
    assert task.size == pytest.approx(np.sqrt(np.mean(np.square(x))))
    assert task.run(LinkModel("gru", 2, 4), 2).count() == 0


def test_tolerances_share_changes_and_run_side_by_side(spark, sf, monkeypatch):
    """changes and features are packed once for the sweep, and no run waits in another one's task."""
    seen, real = [], learning.run_timeline
    monkeypatch.setattr(learning, "run_timeline", lambda *a, **k: seen.append(k["packed"]) or real(*a, **k))
    got = learning.ab_tolerance(spark, sf)
    assert len(seen) == 6 and len({id(p) for p in seen}) == 1 and "events" not in str(seen[0].inputFiles())
    assert "MapInArrow" not in got._jdf.queryExecution().optimizedPlan().toString()
    rows = {(r["alpha"], r["rmax"]): r["pushes"] for r in got.collect()}
    assert len(rows) == 6 and rows[0.2, 1e-4] > rows[0.2, 1e-2]


def test_ranks_are_those_of_drawn_rows(spark):
    """F4 F6 F7: candidates drawn and scored in one pass for all models are the rows of ``negatives``, scored one by one."""
    from dgprop.tasks import ranking

    rng = np.random.default_rng(5)
    z = spark.createDataFrame([(s, n, rng.normal(size=2).tolist()) for s in range(6) for n in range(40) if s or n % 7], "step int, node bigint, z array<double>")
    some = sorted({(int(rng.integers(1, 6)), int(rng.integers(0, 8)), int(rng.integers(10, 40))) for _ in range(150)} | {(5, 99, 12), (5, 2, 77)})
    rows = [(i * 10**15 - 5, *p, "test" if p[0] == 5 else "train") for i, p in enumerate(some)]
    pairs = spark.createDataFrame(rows, "query_id bigint, step int, src bigint, dst bigint, part string")
    test = pairs.filter("part = 'test'")
    train = learning.with_negatives(pairs.filter("part <> 'test'"), 1).filter("part = 'train'")
    rows = learning.with_negatives(test, 6, 5)
    runs = [LinkModel("lstm", 2, 4), LinkModel("gru", 2, 4)]
    whole = link.prepare(z, train.unionByName(rows), 3, 2)
    pool = ranking.pool_of(test)
    task = link.prepare(z, train, 3, 2, more=ranking.asked_ends(test, pool))
    fits = [task.fit(m, 1, 0.01, 0) for m in runs]
    ranks = ranking.ranks(task.sequences, test, pool, [*fits, None], 6, 5)
    got = {r["query_id"]: r for r in ranks.collect()}
    assert len(got) == test.count() > 10 and sum(r["n_others"] for r in got.values()) == rows.filter("label = 0").count()
    assert any(r["rr"] is None for r in got.values())
    for i, m in enumerate(runs):
        want = {r["query_id"]: r["rr"] for r in M.reciprocal_ranks(whole.run(m, 1).withColumn("score", F.round("score", 9))).collect()}
        assert {q: r["rr"][i] for q, r in got.items() if r["rr"] is not None} == pytest.approx(want)
    assert {i: list(ranking.draws(i, 50, 4, 3)) for i in (1, -7)} == {i: [int(hashlib.md5(f"3:{i}:{j}".encode()).hexdigest()[:8], 16) % 50 for j in range(1, 5)] for i in (1, -7)}
