"""Neighbourhood aggregations, walks and heuristics as DataFrame plans."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dgprop.functions.hashing import hash32
from dgprop.operators.graph import degrees
from dgprop.plans.lineage import cut


def conv_layer(edges: DataFrame, features: DataFrame, weights: list[list[float]]) -> DataFrame:
    """relu(D^-1/2 (A + I) D^-1/2 X W), one layer."""
    loops = features.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.lit(1.0).alias("w"))
    all_edges = edges.select("src", "dst", "w").unionByName(loops)
    d = degrees(all_edges)
    n_in, n_out = len(weights), len(weights[0])
    sent = features.join(d, "node").select(F.col("node").alias("src"), *[(F.col("x")[i] / F.sqrt("d")).alias(f"x{i}") for i in range(n_in)]).join(all_edges, "src")
    got = sent.groupBy(F.col("dst").alias("node")).agg(*[F.sum(F.col("w") * F.col(f"x{i}")).alias(f"s{i}") for i in range(n_in)]).join(d, "node")
    out = [F.greatest(F.lit(0.0), sum(F.col(f"s{i}") * weights[i][j] for i in range(n_in)) / F.sqrt("d")) for j in range(n_out)]
    return got.select("node", F.array(*out).alias("z"))


def sampled_mean(edges: DataFrame, features: DataFrame, fanout: int, dim: int, seed: int = 0) -> DataFrame:
    """Own features, then the mean of at most ``fanout`` neighbours, those of the least hash."""
    order = Window.partitionBy("src").orderBy(hash32(seed, F.col("src"), F.col("dst")), "dst")
    some = edges.select("src", "dst").withColumn("k", F.row_number().over(order)).filter(F.col("k") <= fanout)
    got = some.join(features.select(F.col("node").alias("dst"), F.col("x").alias("nx")), "dst").groupBy(F.col("src").alias("node")).agg(*[F.avg(F.col("nx")[i]).alias(f"m{i}") for i in range(dim)])
    means = F.array(*[F.coalesce(F.col(f"m{i}"), F.lit(0.0)) for i in range(dim)])
    return features.join(got, "node", "left").select("node", F.concat("x", means).alias("z"))


def attention(edges: DataFrame, features: DataFrame, own: list[float], other: list[float]) -> DataFrame:
    """Neighbours' mean weighted by softmax of leaky-relu(own . x_dst + other . x_src), by two aggregations."""
    dim = len(own)
    dot = lambda v: sum(F.col("x")[i] * v[i] for i in range(dim))
    s = features.select(F.col("node").alias("src"), dot(other).alias("o"), *[F.col("x")[i].alias(f"x{i}") for i in range(dim)])
    d = features.select(F.col("node").alias("dst"), dot(own).alias("s"))
    raw = F.col("o") + F.col("s")
    scored = edges.select("src", "dst").join(s, "src").join(d, "dst").withColumn("a", F.when(raw > 0, raw).otherwise(0.2 * raw))
    top = scored.groupBy("dst").agg(F.max("a").alias("top"))
    e = scored.join(top, "dst").withColumn("e", F.exp(F.col("a") - F.col("top")))
    return e.groupBy(F.col("dst").alias("node")).agg(F.sum("e").alias("n"), *[F.sum(F.col("e") * F.col(f"x{i}")).alias(f"z{i}") for i in range(dim)]).select("node", F.array(*[F.col(f"z{i}") / F.col("n") for i in range(dim)]).alias("z"))


def recent_neighbours(events: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """For each query (query_id, node, ts_us) the latest ``k`` partners before it: query_id, rank, partner, age_us."""
    found = queries.join(events.select(F.col("src").alias("node"), F.col("dst").alias("partner"), F.col("ts_us").alias("then"), "seq"), "node").filter("then < ts_us")
    order = Window.partitionBy("query_id").orderBy(F.desc("then"), F.desc("seq"))
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "partner", (F.col("ts_us") - F.col("then")).alias("age_us"))


def time_encoding(age_us, n: int, hour_us: float = 3.6e9):
    """Cosines of the age in hours at ``n`` falling frequencies."""
    return F.array(*[F.cos(age_us / hour_us / 10.0**i) for i in range(n)])


#: A node's draws have their least below so many times its mean, but for one walk in exp(20); those are looked for again.
LEAST = 20.0
#: Edges of a node that meet walks in one block, about.
BLOCK_EDGES = 4096


def _in_blocks(edges: DataFrame, *sums: Column) -> tuple[DataFrame, DataFrame]:
    """Edges with their ``block`` and the sums over their node, and each node's number of blocks: no task has to hold a whole hub."""
    sizes = cut(edges.groupBy("src").agg(F.ceil(F.count("*") / BLOCK_EDGES).cast("int").alias("blocks"), *sums))
    block = F.pmod(F.xxhash64(*edges.columns), F.col("blocks")).cast("int")
    return cut(edges.join(sizes, "src").withColumn("block", block).drop("blocks").repartition("src", "block")), sizes.select(F.col("src").alias("node"), "blocks")


def _least_of(now: DataFrame, blocks: DataFrame, keys: list[str], met: Callable[[DataFrame, float | None], DataFrame]) -> DataFrame:
    """For each walk the ``b`` that is least among all edges of its node.

    ``met`` gives the keys, ``b`` and ``sure``, for the edges whose draw is small; only
    where the least of these isn't sure to be the least of all, it is asked for more, at last for all.
    """
    out, left = None, now
    for share in (LEAST, 32 * LEAST, None):
        at = left.join(blocks, "node").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("blocks")
        best = cut(met(at, share).groupBy(*keys).agg(F.min("b").alias("b"), F.max("sure").alias("sure")))
        found = best.filter("sure").select(*keys, "b")
        out = found if out is None else out.unionByName(found)
        left = cut(left.join(found, keys, "left_anti"))
        if left.isEmpty():
            break
    return out


def walks(edges: DataFrame, starts: DataFrame, length: int, repeats: int, seed: int, p: float = 1.0, q: float = 1.0) -> DataFrame:
    """start, rep, pos, node of random walks; the next node has the least -log(u) / weight, with u by hash.

    ``p`` divides the weight of going back, ``q`` that of nodes that are no neighbours of the one before.
    The draws of a node's edges are exponential, so the least one is below a small
    multiple of one over the node's weight: of the edges only those whose hash leaves room for that are kept.
    """
    low, high = min(1.0, 1 / p, 1 / q), max(1.0, 1 / p, 1 / q)
    adj, blocks = _in_blocks(edges.select("src", "dst", "w"), F.sum("w").alias("total"))
    now = starts.select(F.col("node").alias("start"), F.explode(F.sequence(F.lit(0), F.lit(repeats - 1))).alias("rep"), F.col("node"), F.lit(None).cast("bigint").alias("prev"))
    out = now.select("start", "rep", F.lit(0).alias("pos"), "node")

    def met(at: DataFrame, share: float | None, pos: int) -> DataFrame:
        at = at.withColumn("drawn", F.concat(F.concat_ws(":", F.lit(str(seed)), F.col("start"), F.col("rep"), F.lit(pos)), F.lit(":")))
        near_ones = adj.select(F.col("src").alias("node"), "block", "dst", "w", "total", F.col("dst").cast("string").alias("text"))
        if share is not None:
            # The least hash, in hexadecimal digits, of a draw that may be below the multiple, at the greatest of weights.
            least = F.floor(F.exp(F.col("w") / F.col("total") * (-share * high / low)) * 4294967297.0) - 2
            near_ones = near_ones.withColumn("least", F.lpad(F.lower(F.hex(F.greatest(least, F.lit(0)))), 8, "0"))
        digest = F.md5(F.concat("drawn", "text"))
        steps = at.join(near_ones, ["node", "block"])
        if share is not None:
            steps = steps.filter(digest >= F.col("least"))
        steps = steps.select("start", "rep", "node", "prev", "dst", "w", "total", F.conv(F.substring(digest, 1, 8), 16, 10).cast("bigint").alias("h"))
        w = F.col("w")
        if p != 1.0 or q != 1.0:
            near = adj.select(F.col("src").alias("prev"), "dst", F.lit(True).alias("near"))
            steps = steps.join(near, ["prev", "dst"], "left")
            w = F.when(F.col("prev").isNull(), F.col("w")).when(F.col("dst") == F.col("prev"), F.col("w") / p).when(F.col("near"), F.col("w")).otherwise(F.col("w") / q)
        u = (F.col("h") + 1) / F.lit(4294967297.0)
        key = -F.log(u) / w
        sure = F.lit(True) if share is None else key * F.col("total") * low <= share * (1 - 1e-9)
        return steps.select("start", "rep", F.struct(key.alias("key"), "dst", "node").alias("b"), sure.alias("sure"))

    for pos in range(1, length + 1):
        best = _least_of(now, blocks, ["start", "rep"], lambda at, share, pos=pos: met(at, share, pos))
        now = best.select("start", "rep", F.col("b.dst").alias("node"), F.col("b.node").alias("prev"))
        out = out.unionByName(now.select("start", "rep", F.lit(pos).alias("pos"), "node"))
    return out


def temporal_walks(events: DataFrame, starts: DataFrame, length: int, seed: int) -> DataFrame:
    """Walks over events whose times rise: start, pos, node, ts_us. ``events`` holds both directions.

    The next event has the least hash; of a node's many events only those of a small hash are kept.
    """
    both, blocks = _in_blocks(events.select("src", "dst", "ts_us"), F.count("*").alias("n"))
    now = starts.select(F.col("node").alias("start"), "node", F.lit(-1).cast("bigint").alias("at"))
    out = now.select("start", F.lit(0).alias("pos"), "node", F.col("at").alias("ts_us"))

    def met(at: DataFrame, share: float | None, pos: int) -> DataFrame:
        at = at.withColumn("drawn", F.concat(F.concat_ws(":", F.lit(str(seed)), F.col("start"), F.lit(pos)), F.lit(":")))
        most = F.when(F.col("n") > share, F.lpad(F.lower(F.hex(F.floor(F.lit(4294967296.0 * share) / F.col("n")))), 8, "0")).otherwise("g") if share is not None else F.lit("g")
        near_ones = both.select(F.col("src").alias("node"), "block", "dst", "ts_us", F.concat_ws(":", "dst", "ts_us").alias("text"), most.alias("most"))
        digest = F.md5(F.concat("drawn", "text"))
        steps = at.join(near_ones, ["node", "block"]).filter("ts_us > at").filter(digest < F.col("most"))
        return steps.select("start", F.struct(F.conv(F.substring(digest, 1, 8), 16, 10).cast("bigint").alias("key"), "dst", "ts_us").alias("b"), F.lit(True).alias("sure"))

    for pos in range(1, length + 1):
        best = _least_of(now, blocks, ["start"], lambda at, share, pos=pos: met(at, share, pos))
        now = best.select("start", F.col("b.dst").alias("node"), F.col("b.ts_us").alias("at"))
        out = out.unionByName(now.select("start", F.lit(pos).alias("pos"), "node", F.col("at").alias("ts_us")))
    return out


def walk_embedding(walked: DataFrame, dim: int, by: list[str], seed: int = 0) -> DataFrame:
    """Skip-gram over walks, by MLlib: node and z."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    text = walked.groupBy(*by).agg(F.array_sort(F.collect_list(F.struct("pos", F.col("node").cast("string").alias("t")))).alias("s")).select(F.col("s.t").alias("walk"))
    fitted = Word2Vec(vectorSize=dim, minCount=0, windowSize=3, seed=seed, maxIter=1, inputCol="walk", outputCol="z").fit(text)
    return fitted.getVectors().select(F.col("word").cast("bigint").alias("node"), vector_to_array("vector").alias("z"))


def moving_average(layer_by_step: DataFrame, dim: int) -> DataFrame:
    """State after t steps: the mean of the layer's outputs so far, as a running sum over the node's steps."""
    past = Window.partitionBy("node").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return layer_by_step.select("step", "node", F.array(*[F.avg(F.col("z")[i]).over(past) for i in range(dim)]).alias("z"))


def mailbox(events: DataFrame, slots: int) -> DataFrame:
    """Each event leaves its value at both ends; node, rank and value of the latest ``slots`` mails."""
    order = Window.partitionBy("node").orderBy(F.desc("ts_us"), F.desc("seq"))
    mails = events.select(F.explode(F.array("src", "dst")).alias("node"), "ts_us", "seq", "value")
    return mails.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= slots).select("node", "rank", "value")


def common_neighbours(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """src, dst and the neighbours that both have, for the given pairs only."""
    a = pairs.select("src", "dst").distinct()
    first = a.join(edges.select("src", F.col("dst").alias("mid")), "src")
    both = first.join(edges.select(F.col("src").alias("mid"), "dst"), ["mid", "dst"])
    counted = both.groupBy("src", "dst").agg(F.countDistinct("mid").alias("n"))
    return a.join(counted, ["src", "dst"], "left").select("src", "dst", F.coalesce("n", F.lit(0)).alias("n"))


def preferential_attachment(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    d = degrees(edges)
    return pairs.join(d.select(F.col("node").alias("src"), F.col("d").alias("a")), "src").join(d.select(F.col("node").alias("dst"), F.col("d").alias("b")), "dst").select(*pairs.columns, (F.col("a") * F.col("b")).alias("score"))


def recurrence(events: DataFrame) -> DataFrame:
    """seq and how often the same pair was seen before."""
    past = Window.partitionBy("src", "dst").orderBy("ts_us", "seq").rowsBetween(Window.unboundedPreceding, -1)
    return events.select("seq", F.count("*").over(past).alias("seen"))
