"""Mixing sources to target weights by budgets on a tree of domain, language and source.

A budget of tokens flows down the tree.  At every node it is split by the weights
of the children; a child that has less than its share (its tokens times the most
epochs) gets what it has, and its shortage goes to its siblings by their weights
before anything is left to the node's own siblings.  A leaf's tokens are taken
from a sequence of epochs, each all its documents in an order of its own that the
seed fixes: whole epochs first, then the prefix of the next one up to the budget.

Only the leaves' counts come to the driver, and more than ``MOST_LEAVES`` of them
are refused.  Prefixes are found by sums over small ranges of the order and, inside
a range, by a window, so that a leaf with a third of all rows is spread over many
tasks.  What is selected is then all documents up to a leaf's last one in the order,
which needs no shuffle of texts.  Documents count by ``n_tokens`` words.

Null domains, languages and sources are the value ''; empty and null texts have
no tokens and are taken where the prefix reaches them; rows with equal doc_id stand
next to each other in every order and are taken together, where the first of them
is; an empty table gives none.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dgprop.llm.common import SPACES, WORD_GAP, documents, save

LEVELS = ("domain", "lang", "source")
MOST_LEAVES = 100_000
#: Ranges of the orders of all leaves, about; a range has at least ``RANGE_ROWS`` rows, about.
MOST_RANGES, RANGE_ROWS = 1 << 20, 100
_KEY_BITS = 52

Path = tuple[str, ...]


def split_budget(budget: int, weights: dict[str, Fraction], capacity: dict[str, int]) -> dict[str, int]:
    """Whole shares of ``budget`` by weight, none above its capacity; what some can't take goes to the others."""
    given = dict.fromkeys(weights, 0)
    open_names = sorted(n for n in weights if capacity[n] > 0 and weights[n] > 0)
    left = min(budget, sum(capacity[n] for n in open_names))
    while open_names and left:
        total = sum(weights[n] for n in open_names)
        short = [n for n in open_names if capacity[n] * total <= left * weights[n]]
        if short:
            for n in short:
                given[n] = capacity[n]
                left -= capacity[n]
            open_names = [n for n in open_names if n not in short]
            continue
        share = {n: left * weights[n] / total for n in open_names}
        given.update({n: int(s) for n, s in share.items()})
        rest = left - sum(given[n] for n in open_names)
        for n in sorted(open_names, key=lambda n: (int(share[n]) - share[n], n))[:rest]:
            given[n] += 1
        break
    return given


def budgets(tokens: dict[Path, int], weights: dict[Path, float], budget: int, max_epochs: int = 1) -> dict[Path, int]:
    """Tokens for every leaf; weights are by path from the top, 1 where none is given."""
    children: dict[Path, set[str]] = {}
    capacity: dict[Path, int] = {}
    for leaf, n in tokens.items():
        for d in range(len(leaf) + 1):
            capacity[leaf[:d]] = capacity.get(leaf[:d], 0) + n * max_epochs
            if d < len(leaf):
                children.setdefault(leaf[:d], set()).add(leaf[d])
    out: dict[Path, int] = {}
    todo = [((), min(budget, capacity.get((), 0)))]
    while todo:
        path, amount = todo.pop()
        if path not in children:
            out[path] = amount
            continue
        own = {c: Fraction(weights.get((*path, c), 1)).limit_denominator(10**9) for c in children[path]}
        given = split_budget(amount, own, {c: capacity[(*path, c)] for c in own})
        todo += [((*path, c), n) for c, n in given.items()]
    out.pop((), None)
    return out


def words(text: str) -> Column:
    bare = F.btrim(F.coalesce(F.col(text), F.lit("")), F.lit(SPACES))
    return F.when(bare == "", 0).otherwise(F.size(F.split(bare, WORD_GAP))).cast("bigint")


def order_key(seed: int, epoch: Column) -> Column:
    """52 bits that put the documents of an epoch in order."""
    text = F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    return F.conv(F.substring(F.md5(text), 1, _KEY_BITS // 4), 16, 10).cast("bigint")


@dataclass(frozen=True)
class MixPlan:
    """For each leaf its budget, whole epochs, tokens of the next one, and the order's last key that is taken."""

    leaves: DataFrame
    rows: DataFrame


def leaf_columns(domain: Column) -> list[Column]:
    return [F.coalesce(c.cast("string"), F.lit("")).alias(n) for n, c in zip(LEVELS, (domain, F.col("lang"), F.col("source")), strict=True)]


def plan_mix(docs: DataFrame, domain: Column, weights: dict[Path, float], budget: int | float, max_epochs: int = 1, seed: int = 0) -> MixPlan:
    """The plan of a mix; a budget below or equal to 1.0 as a float is a share of all tokens."""
    spark = docs.sparkSession
    leaf = list(LEVELS)
    rows = save(docs.select("doc_id", *leaf_columns(domain), words("text").alias("n_tokens")), "mix-rows")
    stats = rows.groupBy(*leaf).agg(F.sum("n_tokens").alias("tokens"), F.count("*").alias("n_rows")).limit(MOST_LEAVES + 1).collect()
    if len(stats) > MOST_LEAVES:
        raise ValueError(f"more than {MOST_LEAVES} leaves")
    tokens = {tuple(r[c] for c in leaf): r["tokens"] for r in stats}
    total = sum(tokens.values())
    amount = int(total * budget) if isinstance(budget, float) else budget
    given = budgets(tokens, weights, amount, max_epochs)
    n_rows = sum(r["n_rows"] for r in stats)
    each = max(RANGE_ROWS, n_rows // MOST_RANGES)
    table = [(*p, given.get(p, 0), given.get(p, 0) // t if t else 0, given.get(p, 0) % t if t else 0, max(1, n // each)) for p, t, n in sorted((tuple(r[c] for c in leaf), r["tokens"], r["n_rows"]) for r in stats)]
    plan = spark.createDataFrame(table, "domain string, lang string, source string, budget bigint, epochs int, rest bigint, n_ranges bigint")
    keyed = rows.join(F.broadcast(plan), leaf).withColumn("key", order_key(seed, F.col("epochs"))).filter("rest > 0")
    keyed = keyed.withColumn("range", F.floor(F.col("key") / float(1 << _KEY_BITS) * F.col("n_ranges")))
    ahead = Window.partitionBy(*leaf).orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    sums = keyed.groupBy(*leaf, "range").agg(F.sum("n_tokens").alias("in_range"))
    sums = sums.select(*leaf, "range", F.coalesce(F.sum("in_range").over(ahead), F.lit(0)).alias("before"))
    inside = Window.partitionBy(*leaf, "range").orderBy("key", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)
    placed = keyed.withColumn("ahead", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0))).join(sums, [*leaf, "range"])
    last = placed.filter(F.col("before") + F.col("ahead") < F.col("rest")).groupBy(*leaf).agg(F.max("key").alias("last_key"))
    leaves = save(plan.join(last, leaf, "left").select(*leaf, "budget", "epochs", "rest", F.coalesce("last_key", F.lit(-1)).alias("last_key")), "mix-plan")
    return MixPlan(leaves, rows)


def _taken(rows: DataFrame, plan: MixPlan, seed: int) -> DataFrame:
    """Rows with the leaf's columns, once for each epoch that takes them."""
    planned = rows.join(F.broadcast(plan.leaves), list(LEVELS))
    n = F.col("epochs") + F.when(order_key(seed, F.col("epochs")) <= F.col("last_key"), 1).otherwise(0)
    return planned.withColumn("_epochs", n).filter("_epochs > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0), F.col("_epochs") - 1)))


def mix_table(docs: DataFrame, domain: Column, weights: dict[Path, float], budget: int | float, max_epochs: int = 1, seed: int = 0) -> DataFrame:
    """doc_id, domain, lang, source, n_tokens, epoch and the leaf's budget, a row each time a document is taken."""
    plan = plan_mix(docs, domain, weights, budget, max_epochs, seed)
    return _taken(plan.rows, plan, seed).select("doc_id", *LEVELS, "n_tokens", "epoch", "budget")


def mix(docs: DataFrame, domain: Column, weights: dict[Path, float], budget: int | float, max_epochs: int = 1, seed: int = 0) -> DataFrame:
    """The rows of ``docs`` with their columns, as often as they are taken."""
    plan = plan_mix(docs, domain, weights, budget, max_epochs, seed)
    names = {n: f"_leaf_{n}" for n in LEVELS}
    leaves = plan.leaves.select(*[F.col(n).alias(names[n]) for n in LEVELS], *[F.col(c).alias(f"_{c}") for c in ("epochs", "last_key")])
    held = docs.withColumns({names[n]: c for n, c in zip(LEVELS, leaf_columns(domain), strict=True)}).join(F.broadcast(leaves), list(names.values()))
    n = F.col("_epochs") + F.when(order_key(seed, F.col("_epochs")) <= F.col("_last_key"), 1).otherwise(0)
    return held.withColumn("_times", n).filter("_times > 0").withColumn("_epoch", F.explode(F.sequence(F.lit(0), F.col("_times") - 1))).select(*docs.columns)


def source_group(n: int = 4) -> Column:
    """A domain for tables that have none: sources dealt to ``n`` groups by the number in their name."""
    number = F.regexp_extract(F.coalesce("source", F.lit("")), "([0-9]{1,9})$", 1)
    return F.concat(F.lit("group"), F.when(number == "", 0).otherwise(F.expr("try_cast(regexp_extract(coalesce(source, ''), '([0-9]{1,9})$', 1) AS bigint)") % n))


#: Target weights of the query: domains 4 to 1, English twice each other language, sources alike.
WEIGHTS: dict[Path, float] = {(f"group{i}",): 4.0 - i for i in range(4)} | {(f"group{i}", "en"): 2.0 for i in range(4)}


def op2_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_table(documents(spark, sf_dir), source_group(), WEIGHTS, 0.6, max_epochs=3, seed=7)
