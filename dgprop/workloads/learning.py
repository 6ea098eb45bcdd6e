"""Models and the experiments end to end."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.functions.hashing import hash32, sql_uniform
from dgprop.models.networks import ENCODERS, ClassModel, LinkModel, states
from dgprop.operators import graph as G
from dgprop.operators import metrics as M
from dgprop.operators import propagate as pr
from dgprop.operators.filters import FilterSpec
from dgprop.operators.timeline import pack, run_timeline
from dgprop.plans.lineage import at_once, stored
from dgprop.sources import tables as T
from dgprop.tasks import link, node, ranking, splits
from dgprop.workloads import sqltext as q
from dgprop.workloads.graphs import daily, document_edges, event_edges, random_x
from dgprop.workloads.registry import query, r, sql_r

LOW, HIGH = FilterSpec.restart(0.2), FilterSpec.alternating(0.2)
DIM, LENGTH = 8, 4


# Forward passes with weights from a hash

_BIAS = 0.1


def _weight(name: str, i: int, j: int) -> str:
    return sql_uniform(f"'{name}:{i}:{j}'")


def _hash_weights(name: str, a: int, b: int) -> np.ndarray:
    import hashlib

    return np.array([[int(hashlib.md5(f"{name}:{i}:{j}".encode()).hexdigest()[:8], 16) / 4294967296.0 - 0.5 for j in range(b)] for i in range(a)])


_EN = f"SELECT src AS node FROM ({q.EVENT_EDGES}) GROUP BY src"
_X4 = "SELECT node, " + ", ".join(f"max(CASE WHEN dim = {i} THEN x END) AS x{i}" for i in range(4)) + f" FROM ({q.features(_EN, 4)}) GROUP BY node"


def _linear(name: str, inputs: list[str], j: int) -> str:
    return " + ".join(f"{x} * {_weight(name, i, j)}" for i, x in enumerate(inputs)) + f" + {_BIAS}"


@query(f"SELECT node, {sql_r('1 / (1 + exp(-(' + _linear('l', ['x0', 'x1', 'x2', 'x3'], 0) + ')))')} AS p FROM ({_X4})")
def md_logistic_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = _hash_weights("l", 4, 1)
    x = random_x(event_edges(spark, sf_dir), 4)
    z = sum(F.col("x")[i] * float(w[i, 0]) for i in range(4)) + _BIAS
    return x.select("node", r(1 / (1 + F.exp(-z))).alias("p"))


_H = ", ".join(f"greatest(0.0, {_linear('h', ['x0', 'x1', 'x2', 'x3'], j)}) AS h{j}" for j in range(3))
_O = ", ".join(f"exp({_linear('o', ['h0', 'h1', 'h2'], j)}) AS e{j}" for j in range(3))


@query(f"SELECT node, {', '.join(sql_r(f'e{j} / (e0 + e1 + e2)') + f' AS p{j}' for j in range(3))} FROM (SELECT node, {_O} FROM (SELECT node, {_H} FROM ({_X4})))")
def md_mlp_forward(spark: SparkSession, sf_dir: str) -> DataFrame:
    params = {"mlp0_w": _hash_weights("h", 4, 3), "mlp0_b": np.full(3, _BIAS), "mlp1_w": _hash_weights("o", 3, 3), "mlp1_b": np.full(3, _BIAS)}
    model = ClassModel([4, 3, 3])

    def forward(parts):
        import pandas as pd

        for part in parts:
            if len(part):
                p = model.scores(params, part)
                yield pd.DataFrame({"node": part["node"], "p0": p[:, 0], "p1": p[:, 1], "p2": p[:, 2]})

    out = random_x(event_edges(spark, sf_dir), 4).mapInPandas(forward, "node bigint, p0 double, p1 double, p2 double")
    return out.select("node", *[r(f"p{j}").alias(f"p{j}") for j in range(3)])


def _forward_query(kind: str) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        z = daily_low(spark, sf_dir, 2)
        rows = link.padded(link.deltas(z), LENGTH, 2)
        params = ENCODERS[kind][0](np.random.default_rng(0), 2, 4)

        def forward(batches):
            import pyarrow as pa

            for batch in batches:
                if batch.num_rows:
                    x, m = (batch.column(c).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, LENGTH, -1) for c in ("x", "m"))
                    h = states(kind, params, x, m[:, :, 0].astype(float))
                    yield pa.RecordBatch.from_arrays([batch.column("step"), batch.column("node"), pa.array(h[:, 0].copy()), pa.array(h.sum(1))], ["step", "node", "h0", "total"])

        return rows.withColumn("x", F.flatten("x")).mapInArrow(forward, "step int, node bigint, h0 double, total double").select("step", "node", r("h0", 4).alias("h0"), r("total", 4).alias("total"))

    run.__name__ = f"md_{kind}_forward"
    query()(run)


for _kind in ENCODERS:
    _forward_query(_kind)


# Experiments

_PASS = {"low": [LOW], "two": [LOW, HIGH]}


def daily_low(spark: SparkSession, sf_dir: str, dim: int, bands: str = "low") -> DataFrame:
    deltas = daily(spark, sf_dir)
    return run_timeline(deltas, random_x(deltas, dim), _PASS[bands], 1e-4, dim).representations


def with_negatives(pairs: DataFrame, k: int, seed: int = 3) -> DataFrame:
    """Positives with label 1 and ``k`` others each with label 0, all with the positive's part."""
    pool = splits.indexed(pairs.select(F.col("dst").alias("node")).distinct())
    no = splits.negatives(pairs, pool, k, seed, pairs).join(pairs.select("query_id", "part"), "query_id")
    return pairs.select("query_id", "step", "src", "dst", F.lit(1).alias("label"), "part").unionByName(no.select("query_id", "step", "src", "dst", "label", "part"))


def _pairs(events: DataFrame) -> DataFrame:
    """Each pair once in a step."""
    return events.select("step", "src", "dst").distinct().select(F.xxhash64("step", "src", "dst").alias("query_id"), "step", "src", "dst")


@dataclass(frozen=True)
class Variant:
    """How links are scored; ``names`` are columns of the result."""

    kind: str = "lstm"
    bands: str = "low"
    change: str = "diff"
    names: tuple[tuple[str, str], ...] = ()


def continuous_links(events: DataFrame, variants: list[Variant], epochs: int = 3, x: DataFrame | None = None, dim: int = DIM, seed: int = 0) -> DataFrame:
    """Average precision of next-step links of the test part, in both settings; events have seq, step, src, dst, kind, w.

    All variants share the representations (the low band is the first half of both), the
    pairs and the negatives; their models are fitted at the same time.
    """
    deltas = stored(G.net_deltas(events))
    wide = "two" if any(v.bands == "two" for v in variants) else "low"
    z = stored(run_timeline(deltas, random_x(deltas, dim) if x is None else x, _PASS[wide], 1e-4, dim).representations)
    pairs = stored(splits.time_split(_pairs(events)))
    both = stored(with_negatives(pairs, 1).filter("part <> 'valid'"))
    settings = ("transductive", "inductive")
    asked = stored(reduce(DataFrame.unionByName, [splits.in_setting(pairs, s).select("query_id", F.lit(s).alias("setting")) for s in settings]))
    tasks = {}
    for v in variants:
        if (v.bands, v.change) not in tasks:
            d = 1 if v.change != "diff" else dim * len(_PASS[v.bands])
            mine = z.withColumn("z", F.slice("z", 1, dim)) if v.bands != wide else z
            tasks[v.bands, v.change] = link.prepare(mine, both, LENGTH, d, v.change), d

    def scored(v: Variant) -> DataFrame:
        task, d = tasks[v.bands, v.change]
        return task.run(LinkModel(v.kind, d, 8), epochs, seed=seed).select("query_id", "label", "score")

    out = []
    for v, rows in zip(variants, at_once(scored, variants), strict=True):
        rows = stored(rows.join(asked, "query_id"))
        found = M.average_precision(rows, ["setting"]).join(rows.groupBy("setting").agg(F.count("*").alias("n")), "setting")
        every = rows.sparkSession.createDataFrame([(s,) for s in settings], "setting string").join(found, "setting", "left")
        out.append(every.select("setting", r("average_precision").alias("average_precision"), F.coalesce("n", F.lit(0)).alias("n"), *[F.lit(value).alias(name) for name, value in v.names]))
    return reduce(DataFrame.unionByName, out)


@query()
def lp_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users and items; the tables are near random, so about one half is the honest value."""
    return continuous_links(T.interactions(spark, sf_dir).withColumn("step", G.bucket()), [Variant()])


def planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events whose items follow the user's community four times in five; communities switch at mid-time."""
    e = T.interactions(spark, sf_dir).withColumn("step", G.bucket())
    middle = e.agg(F.floor((F.min("step") + F.max("step")) / 2)).head()[0]
    community = (F.col("src") + F.when(F.col("step") > middle, 1).otherwise(0)) % 4
    own = F.pmod(hash32("own", F.col("seq")), F.lit(100)) < 80
    item = F.pmod(hash32("item", F.col("seq")), F.lit(25))
    any_community = F.pmod(hash32("any", F.col("seq")), F.lit(4))
    return e.withColumn("dst", T.ITEM + item * 4 + F.when(own, community).otherwise(any_community))


def group_features(events: DataFrame) -> DataFrame:
    """Items know their group of four, users nothing."""
    nodes = G.nodes_of(events)
    item = F.col("node") >= T.ITEM
    return nodes.select("node", F.array(*[F.when(item & ((F.col("node") - T.ITEM) % 4 == i), 1.0).otherwise(0.0) for i in range(4)]).alias("x"))


@query()
def lp_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where there is something to learn: average precision by model and band, on the planted events."""
    events = stored(planted(spark, sf_dir).select("seq", "step", "kind", "src", "dst", "w"))
    variants = [Variant("lstm", b, names=(("model", "lstm"), ("bands", b))) for b in ("low", "two")]
    return continuous_links(events, variants, epochs=8, x=group_features(events), dim=4)


#: Negatives of each pair that is ranked; a source with fewer free targets gets all of them.
RANKED = 1000
SEEDS = (0, 1, 2)


def ranked_links(deltas: DataFrame, pairs: DataFrame, kinds: tuple[str, ...], epochs: int = 1, seeds: tuple[int, ...] = SEEDS) -> DataFrame:
    """By sequence model: mean reciprocal rank, a mean over the test steps, its mean and deviation over seeds; both bands."""
    deltas = stored(deltas)
    z = stored(run_timeline(deltas, random_x(deltas, 4), [LOW, HIGH], 1e-3, 4).representations)
    pairs = stored(splits.time_split(pairs))
    train, test = with_negatives(pairs.filter("part <> 'test'"), 1).filter("part = 'train'"), pairs.filter("part = 'test'")
    pool = ranking.pool_of(test)
    task = link.prepare(z, train, 3, 8, more=ranking.asked_ends(test, pool))
    runs = [(kind, seed) for kind in kinds for seed in seeds]
    fits = at_once(lambda run: task.fit(LinkModel(run[0], 8, 8), epochs, 0.01, run[1]), runs)
    ranks = stored(ranking.ranks(task.sequences, test, pool, fits, RANKED, 5))
    candidates = ranks.agg((F.sum("n_others") / (F.sum("n_others") + F.count("*"))).alias("share")).select(r(F.col("share") / (1 - F.col("share"))).alias("mean_negatives"))
    by_step = ranks.filter("rr IS NOT NULL").groupBy("step").agg(*[F.avg(F.col("rr")[i]).alias(f"m{i}") for i in range(len(runs))])
    each = by_step.agg(F.array(*[F.struct(F.lit(kind).alias("model"), F.avg(f"m{i}").alias("mrr")) for i, (kind, _) in enumerate(runs)]).alias("runs")).select(F.inline("runs"))
    return each.groupBy("model").agg(r(F.avg("mrr")).alias("mrr"), r(F.coalesce(F.stddev_samp("mrr"), F.lit(0.0))).alias("deviation"), F.count("*").alias("seeds")).join(candidates)


@query()
def lp_monthly_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers that meet in an order, by month; the three sequence models."""
    co = stored(T.co_suppliers(spark, sf_dir))
    deltas = G.mirrored(co.withColumnRenamed("w", "dw"), "dw").select("step", "src", "dst", "dw")
    return ranked_links(deltas, _pairs(co), tuple(ENCODERS))


@query()
def lp_returns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and suppliers with deletions, by month; the three sequence models."""
    rows = T.trades_with_returns(spark, sf_dir).withColumn("step", G.month())
    deltas = G.clamp_deltas(G.net_deltas(rows))[0]
    return ranked_links(deltas, _pairs(rows.filter("kind = 'add_edge'")), tuple(ENCODERS))


@query()
def lp_biweekly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and suppliers in steps of two weeks; the three sequence models."""
    rows = T.trades(spark, sf_dir, "supplier").withColumn("step", G.bucket(14 * T.DAY_US))
    return ranked_links(G.net_deltas(rows), _pairs(rows), tuple(ENCODERS))


@query()
def lp_trades(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and parts by month: average precision in both settings."""
    return continuous_links(T.trades(spark, sf_dir).withColumn("step", G.month()).select("seq", "step", "kind", "src", "dst", "w"), [Variant()])


@query()
def nc_returns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether a trade's goods come back, from the customer's and the part's representations of the month before."""
    trades = T.trades(spark, sf_dir).withColumn("step", G.month())
    deltas = stored(G.net_deltas(trades.select("seq", "step", "kind", "src", "dst", "w")))
    z = stored(run_timeline(deltas, random_x(deltas, DIM), [LOW], 1e-4, DIM).representations)
    known = trades.select(F.col("seq").alias("id"), "src", "dst", (F.col("step") - 1).alias("step"), (F.col("l_returnflag") == "R").cast("int").alias("label"))
    side = lambda end, name: z.select("step", F.col("node").alias(end), F.col("z").alias(name))
    rows = known.join(side("src", "zs"), ["step", "src"]).join(side("dst", "zd"), ["step", "dst"]).select("id", F.concat("zs", "zd").alias("x"), "label", "step")
    # Counted by step, fitted and scored: the joins are made once for all three.
    split = splits.time_split(stored(rows.select(F.col("id").alias("query_id"), "step", "x", "label"))).withColumnRenamed("query_id", "id")
    return auc_metrics(node.run(split, ClassModel([2 * DIM, 32, 32, 2]), 3))


def class_metrics(scored: DataFrame) -> DataFrame:
    test = scored.filter("part = 'test'")
    return M.f1(test).join(test.agg(F.count("*").alias("n"))).select(r("f1_micro").alias("f1_micro"), r("f1_macro").alias("f1_macro"), "n")


def auc_metrics(scored: DataFrame) -> DataFrame:
    test = scored.filter("part = 'test'").withColumn("score", F.round("score", 9))
    return M.roc_auc(test).join(M.average_precision(test)).select(r("roc_auc").alias("roc_auc"), r("average_precision").alias("average_precision"))


def causal_walk_links(spark: SparkSession, sf_dir: str, pool: str) -> DataFrame:
    """Average precision of the test pairs from walks back in time, set-coded, pooled and scored by a dense head."""
    import pandas as pd

    from dgprop.baselines.neural import causal_walk_features
    from dgprop.models.networks import fit_rows

    e = stored(T.interactions(spark, sf_dir).withColumn("step", G.bucket()))
    # A pair and its others are asked for when it first meets in the step.
    first = e.groupBy(F.xxhash64("step", "src", "dst").alias("query_id")).agg(F.min("ts_us").alias("ts_us"))
    rows = with_negatives(stored(splits.time_split(_pairs(e))), 1).join(first, "query_id")

    def work(pairs: pd.DataFrame, events: pd.DataFrame) -> pd.DataFrame:
        pairs = pairs.sort_values(["query_id", "label", "dst"], ignore_index=True)
        events = events[["a", "b", "t"]].set_axis(["src", "dst", "ts_us"], axis=1)
        pairs["x"] = list(causal_walk_features(pairs, events, 4, 2, pool))
        model = ClassModel([18, 16, 2])
        params = fit_rows(model, pairs[pairs["part"] == "train"], 5, 256, 0.01, 0)
        test = pairs[pairs["part"] == "test"]
        return test[["label"]].assign(score=model.scores(params, test)[:, 1])

    one = F.lit(0).alias("one")
    scored = stored(rows).select("*", one).groupBy("one").cogroup(e.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("ts_us").alias("t"), one).groupBy("one")).applyInPandas(work, "label int, score double")
    return M.average_precision(scored.withColumn("score", F.round("score", 9))).select(F.lit(pool).alias("pool"), r("average_precision").alias("average_precision"))


@query()
def lp_causal_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Walks pooled by mean and by attention."""
    return causal_walk_links(spark, sf_dir, "mean").unionByName(causal_walk_links(spark, sf_dir, "attn"))


@query()
def nc_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Will the user's event be an error?  From the latest representation before it, a three-layer network."""
    from dgprop.operators.sequences import as_of

    z = daily_low(spark, sf_dir, DIM)
    e = T.interactions(spark, sf_dir).withColumn("step", G.bucket())
    asked = e.select(F.col("seq").alias("query_id"), F.col("src").alias("node"), (F.col("step") - 1).alias("step"))
    label = e.select(F.col("seq").alias("query_id"), "step", (F.col("event_type") == "error").cast("int").alias("label"), "src", "dst")
    parts = splits.time_split(label)
    # Counted, fitted and scored.
    rows = stored(as_of(z, asked).select("query_id", "z").join(parts, "query_id").select(F.col("query_id").alias("id"), F.col("z").alias("x"), "label", "part"))
    return auc_metrics(node.run(rows, ClassModel([DIM, 16, 16, 2]), 5))


def _document_rows(spark: SparkSession, sf_dir: str, dim: int = 16) -> DataFrame:
    """Filtered hashed bags of words on documents and shared lines: id (doc_id), x, text's columns."""
    docs = T.table(spark, sf_dir, "documents")
    cell = F.pmod(hash32("bag", F.col("w")), F.lit(dim))
    words = docs.select("doc_id", F.explode(F.split(F.lower(F.coalesce("text", F.lit(""))), "[^\\p{L}]+")).alias("w"))
    counts = words.groupBy("doc_id").agg(F.count("*").alias("n"), *[F.sum(F.when(cell == i, 1.0).otherwise(0.0)).alias(f"c{i}") for i in range(dim)])
    x = counts.select((F.col("doc_id") + T.DOCUMENT).alias("node"), F.array(*[F.col(f"c{i}") / F.col("n") for i in range(dim)]).alias("x"))
    e = stored(document_edges(spark, sf_dir))
    lines = G.nodes_of(e).filter(F.col("node") >= T.LINE).select("node", F.array_repeat(F.lit(0.0), dim).alias("x"))
    both = stored(x.unionByName(lines))
    half = FilterSpec.restart(0.5)
    z = pr.push(e, pr.init_state(both, e, [half], dim), [half], 1e-3, dim).readout()
    return z.filter(F.col("node") < T.LINE).select((F.col("node") - T.DOCUMENT).alias("id"), F.transform("z", lambda v: v * 20).alias("x"))


@query()
def nc_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of documents, four classes."""
    langs = T.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), (F.array_position(F.array(*[F.lit(x) for x in ("de", "en", "es", "fr")]), F.col("lang")) - 1).cast("int").alias("label"))
    rows = node.hash_split(_document_rows(spark, sf_dir).join(langs.filter("label >= 0"), "id"))
    return class_metrics(node.run(rows, ClassModel([16, 32, 32, 4]), 40))


@query()
def nc_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The quality label that some documents have."""
    known = T.table(spark, sf_dir, "labels").select(F.col("doc_id").alias("id"), F.col("quality").alias("label"))
    rows = node.hash_split(_document_rows(spark, sf_dir).join(known, "id"))
    return auc_metrics(node.run(rows, ClassModel([16, 16, 16, 2]), 40))


@query()
def nc_quality_logistic(spark: SparkSession, sf_dir: str) -> DataFrame:
    known = T.table(spark, sf_dir, "labels").select(F.col("doc_id").alias("id"), F.col("quality").alias("label"))
    rows = node.hash_split(_document_rows(spark, sf_dir).join(known, "id"))
    return auc_metrics(node.logistic(rows))


@query()
def nc_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The brand of parts, 25 classes, from the latest of yearly steps of customers' trades over the whole vectors; chance is about 0.04."""
    trades = T.trades(spark, sf_dir).withColumn("step", F.year(F.timestamp_micros("ts_us"))).select("seq", "step", "kind", "src", "dst", "w")
    deltas = stored(G.net_deltas(trades))
    v = T.table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    n, width = v.agg(F.count("*"), F.coalesce(F.max(F.size("x")), F.lit(1))).head()
    parts = T.table(spark, sf_dir, "part").select("p_partkey", (F.col("p_partkey") % n).alias("vec_id"), "p_brand")
    px = parts.join(v, "vec_id").select((F.col("p_partkey") + T.PART).alias("node"), "x")
    others = G.nodes_of(trades).join(px.select("node"), "node", "left_anti")
    x = stored(px.unionByName(others.select("node", F.array_repeat(F.lit(0.0), width).alias("x"))))
    # Each node has a row in every step, so the latest one is that of the last step.
    latest = run_timeline(deltas, x, [LOW], 1e-3, width, emit="last").representations.filter(F.col("node") >= T.PART)
    brand = F.coalesce(F.expr("try_cast(regexp_extract(p_brand, '([0-9]+)$', 1) AS int)") - 1, F.lit(0))
    label = parts.select((F.col("p_partkey") + T.PART).alias("node"), F.col("p_partkey").alias("id"), F.pmod(brand, F.lit(25)).alias("label"))
    rows = node.hash_split(stored(latest.join(label, "node").select("id", F.col("z").alias("x"), "label")))
    return class_metrics(node.run(rows, ClassModel([width, 32, 32, 25]), 10))


# Sweeps and ablations


@query()
def ab_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Low against both bands, three encoders, on the planted events."""
    events = stored(planted(spark, sf_dir).select("seq", "step", "kind", "src", "dst", "w"))
    variants = [Variant(k, b, names=(("model", k), ("bands", b))) for k in ("gru", "transformer") for b in ("low", "two")]
    return continuous_links(events, variants, epochs=4, x=group_features(events), dim=4).filter("setting = 'transductive'")


@query()
def ab_changes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The change as difference, length or cosine."""
    events = stored(planted(spark, sf_dir).select("seq", "step", "kind", "src", "dst", "w"))
    variants = [Variant("gru", change=c, names=(("change", c),)) for c in ("diff", "l2", "cosine")]
    return continuous_links(events, variants, epochs=4, x=group_features(events), dim=4)


@query()
def ab_tolerance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A smaller tolerance costs more pushes; a smaller restart too."""
    deltas = stored(daily(spark, sf_dir))
    x = random_x(deltas, 1)
    packed = pack(deltas, x)

    def costs(run: tuple[float, float]) -> DataFrame:
        alpha, rmax = run
        stats = run_timeline(deltas, x, [FilterSpec.restart(alpha)], rmax, 1, packed=packed).stats
        # Worked out here: a union of single partitions is one task, in which the runs would wait for each other.
        return stored(stats.agg(F.sum("pushes").alias("pushes"), F.sum("edges_touched").alias("edges_touched"), F.sum("rounds").cast("bigint").alias("rounds")).select(F.lit(alpha).alias("alpha"), F.lit(rmax).alias("rmax"), "*"))

    return reduce(DataFrame.unionByName, at_once(costs, [(alpha, rmax) for alpha in (0.2, 0.5) for rmax in (1e-2, 1e-3, 1e-4)]))
