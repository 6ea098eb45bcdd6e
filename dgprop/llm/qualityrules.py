"""Weakly supervised quality filtering: rules vote, their accuracies are learnt.

Every rule looks at counts of one document and votes good (1), bad (-1) or
abstains (0).  Documents with equal votes are alike to the model, so one
aggregation to vote patterns (at most 3 to the number of rules, whatever the
input) holds all that expectation-maximisation needs.  It estimates, for each
rule, how often it votes each way on good documents and on each of several kinds
of bad ones (repetition is another fault than symbols, and one class for both
takes the rarer fault for good), and the shares of the kinds.  A fault
that only one rule sees, and that is rare, can't be told from that rule's errors.  On every kind a
vote is the likelier, against good documents, the worse it is, so a bad vote
always lowers the posterior probability of "good", which takes the place of a
filter that all rules must pass.

All counts are row-local DataFrame expressions: no shuffle but that of the
patterns.  Null and empty texts have no words, fail the base rule and are not
kept; repeated rows, and rows without doc_id, are judged alike; a posterior that
equals the threshold is enough; a very long text is one row of words and windows at a time; other columns are passed on by
``keep_good`` and ignored by ``judge``; an empty table gives an empty result.
Windows of three words are compared by a 64-bit hash.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.llm.common import SPACES, WORD_GAP, documents, save

SYMBOLS = "#*$%&|<>"
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_distinct_words", "n_letters"]


def with_counts(docs: DataFrame, prefix: str = "") -> DataFrame:
    """Add the counts that rules use, under ``prefix`` + their names."""
    p = prefix
    text = F.coalesce(F.col("text"), F.lit(""))
    bare = F.btrim(text, F.lit(SPACES))
    rows = docs.withColumn(f"{p}words", F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, WORD_GAP)))
    words = F.col(f"{p}words")
    n = F.size(words)
    windows = F.arrays_zip(
        F.slice(words, 1, F.greatest(n - 2, F.lit(0))).alias("a"),
        F.slice(words, 2, F.greatest(n - 2, F.lit(0))).alias("b"),
        F.slice(words, 3, F.greatest(n - 2, F.lit(0))).alias("c"),
    )
    rows = rows.withColumn(f"{p}windows", F.sort_array(F.transform(windows, lambda x, i: F.struct(F.xxhash64(x["a"], x["b"], x["c"]).alias("h"), i.alias("i")))))
    w = F.col(f"{p}windows")
    # Neighbours in hash order that are equal: both windows stand in the text twice or more.
    pairs = F.zip_with(w, F.slice(w, 2, F.greatest(F.size(w) - 1, F.lit(0))), lambda x, y: F.struct((x["h"] == y["h"]).alias("same"), x["i"].alias("i"), y["i"].alias("j")))
    covered = F.flatten(F.transform(F.filter(pairs, lambda x: x["same"]), lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2, x["j"], x["j"] + 1, x["j"] + 2)))
    lines = F.filter(F.split(text, "\n"), lambda x: F.btrim(x, F.lit(SPACES)) != "")
    rows = rows.withColumn(f"{p}lines", lines)
    line_col = F.col(f"{p}lines")
    count = {
        "n_words": n,
        "word_chars": F.length(F.translate(text, SPACES, "")),
        "n_symbols": F.length(text) - F.length(F.translate(text, SYMBOLS, "")),
        "n_dup_lines": F.size(line_col) - F.size(F.array_distinct(line_col)),
        "n_repeat_words": F.size(F.array_distinct(covered)),
        "n_lines": F.size(line_col),
        "n_distinct_words": F.size(F.array_distinct(words)),
        "n_letters": F.length(F.regexp_replace(text, "[^\\p{L}]+", "")),
    }
    rows = rows.withColumns({f"{p}{k}": v.cast("bigint") for k, v in count.items()})
    return rows.drop(f"{p}words", f"{p}windows", f"{p}lines")


@dataclass(frozen=True)
class Rule:
    """Votes bad beyond ``bad`` and good within ``good``; both are conditions on the counts."""

    name: str
    good: str
    bad: str

    def vote(self, prefix: str = "") -> Column:
        return F.expr(f"CASE WHEN {self._on(self.bad, prefix)} THEN -1 WHEN {self._on(self.good, prefix)} THEN 1 ELSE 0 END")

    @staticmethod
    def _on(condition: str, prefix: str) -> str:
        for c in COUNTS if prefix else []:
            condition = condition.replace(f"{{{c}}}", f"`{prefix}{c}`")
        return condition.replace("{", "`").replace("}", "`")


#: Conditions in whole numbers; names of counts stand in braces.
RULES = (
    Rule("length", "{n_words} BETWEEN 50 AND 100000", "{n_words} < 20"),
    Rule("word_length", "{word_chars} BETWEEN 3 * {n_words} AND 10 * {n_words}", "{word_chars} < 2 * {n_words} OR {word_chars} > 14 * {n_words}"),
    Rule("symbols", "100 * {n_symbols} <= {n_words}", "100 * {n_symbols} > 10 * {n_words}"),
    Rule("repeated_lines", "{n_dup_lines} = 0", "100 * {n_dup_lines} > 30 * {n_lines}"),
    Rule("repeated_windows", "100 * {n_repeat_words} <= 10 * {n_words}", "100 * {n_repeat_words} > 30 * {n_words}"),
    Rule("variety", "100 * {n_distinct_words} >= 30 * {n_words}", "100 * {n_distinct_words} < 15 * {n_words}"),
    Rule("letters", "100 * {n_letters} >= 85 * {word_chars}", "100 * {n_letters} < 65 * {word_chars}"),
)
#: How much likelier a bad vote is at least than an abstention, on any kind of bad documents against good ones.
LEAST_LIFT = 1.1
BASE_FAILED = "{n_words} < 50 OR 100 * {n_repeat_words} > 50 * {n_words}"


@dataclass(frozen=True)
class QualityModel:
    """The share of good documents and of each kind of bad ones, and the chances of the votes -1, 0 and 1 of each rule on them."""

    good_share: float
    good_votes: tuple[tuple[float, float, float], ...]
    bad_shares: tuple[float, ...]
    bad_votes: tuple[tuple[tuple[float, float, float], ...], ...]

    def chance(self, votes: tuple[int, ...]) -> float:
        """The probability of "good", given the votes."""
        odds = 0.0
        for share, kind in zip(self.bad_shares, self.bad_votes, strict=True):
            log = math.log(share) - math.log(self.good_share)
            for v, bad, good in zip(votes, kind, self.good_votes, strict=True):
                log += math.log(bad[v + 1]) - math.log(good[v + 1])
            odds += math.exp(min(log, 700.0))
        return 1 / (1 + odds)

    def posterior(self, votes: list[Column], patterns: list[tuple[tuple[int, ...], int]]) -> Column:
        """The probability of "good" for votes that are among the patterns."""

        def code(v):
            return sum(((x + 1) * 3**j for j, x in enumerate(v)), start=0)

        # The frequent ones are found first.
        listed = sorted(patterns, key=lambda p: (-p[1], p[0])) or [((0,) * len(votes), 0)]
        at = F.array_position(F.lit([code(v) for v, _ in listed]).cast("array<bigint>"), code([v.cast("bigint") for v in votes]))
        return F.get(F.lit([self.chance(v) for v, _ in listed]), (at - 1).cast("int"))


def _ordered(chances: np.ndarray, good: np.ndarray) -> np.ndarray:
    """The likeliest chances of -1, 0 and 1 whose ratios to the good ones' fall from vote to vote, by ``LEAST_LIFT`` after -1."""
    base = good * np.array([LEAST_LIFT, 1, 1])
    base = base / base.sum()
    blocks: list[list[float]] = []
    for p, w in zip(chances, base, strict=True):
        blocks.append([p, w, 1])
        while len(blocks) > 1 and blocks[-2][0] * blocks[-1][1] < blocks[-1][0] * blocks[-2][1]:
            last = blocks.pop()
            blocks[-1] = [x + y for x, y in zip(blocks[-1], last, strict=True)]
    return base * np.concatenate([[p / w] * k for p, w, k in blocks])


def _maximise(hot: np.ndarray, n: np.ndarray, belief: np.ndarray, rounds: int, smooth: float):
    """Shares, chances (class, rule, vote), beliefs and log-likelihood; class 0 is the good one."""
    for _ in range(rounds):
        mass = belief * n[:, None]
        share = mass.sum(0) + smooth
        share /= share.sum()
        chance = np.einsum("pc,pjv->cjv", mass, hot) + smooth
        chance /= chance.sum(2, keepdims=True)
        for kind in chance[1:]:
            for j, good in enumerate(chance[0]):
                kind[j] = _ordered(kind[j], good)
        each = np.log(share) + np.einsum("pjv,cjv->pc", hot, np.log(chance))
        total = np.logaddexp.reduce(each, axis=1)
        new = np.exp(each - total[:, None])
        changed, belief = np.abs(new - belief).max(), new
        if changed < 1e-9:
            break
    return share, chance, belief, float((n * total).sum())


def fit(patterns: list[tuple[tuple[int, ...], int]], rounds: int = 100, smooth: float = 1.0) -> QualityModel:
    """Expectation-maximisation over (votes, documents with them).

    It starts from the balance of the votes and one kind of bad documents.  A
    further kind starts from the documents that are held good though one of the
    rules votes bad; the best of these starts is taken as long as the Bayesian
    information criterion gains.  ``smooth`` documents are added to each count.
    Without documents all chances are even.
    """
    patterns = sorted(patterns)
    if not patterns:
        even = ((1 / 3,) * 3,) * len(RULES)
        return QualityModel(0.5, even, (0.5,), (even,))
    votes, n = np.array([v for v, _ in patterns]), np.array([c for _, c in patterns], float)
    n_rules = votes.shape[1]
    hot = (votes[:, :, None] == np.array([-1, 0, 1])).astype(float)
    good = 1 / (1 + np.exp(-votes.sum(1).astype(float)))
    best = _maximise(hot, n, np.stack([good, 1 - good], 1), rounds, smooth)
    cost = (1 + 2 * n_rules) * math.log(n.sum()) / 2
    while best[2].shape[1] <= n_rules:
        tries = []
        for j in range(n_rules):
            moved = np.where(votes[:, j] < 0, best[2][:, 0], 0)
            belief = np.maximum(np.column_stack([best[2], moved]), 1e-6)
            belief[:, 0] = np.maximum(best[2][:, 0] - moved, 1e-6)
            tries.append(_maximise(hot, n, belief / belief.sum(1, keepdims=True), rounds, smooth))
        top = max(tries, key=lambda t: t[3])
        if top[3] - best[3] <= cost:
            break
        best = top
    share, chance = best[0].tolist(), [tuple(map(tuple, c)) for c in best[1].tolist()]
    return QualityModel(share[0], chance[0], tuple(share[1:]), tuple(chance[1:]))


def vote_patterns(counts: DataFrame, rules: tuple[Rule, ...] = RULES, prefix: str = "") -> list[tuple[tuple[int, ...], int]]:
    votes = [r.vote(prefix).alias(f"v{j}") for j, r in enumerate(rules)]
    rows = counts.select(*votes).groupBy(*[f"v{j}" for j in range(len(rules))]).count().collect()
    return [(tuple(r[:-1]), r[-1]) for r in rows]


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES, threshold: float = 0.5) -> DataFrame:
    """doc_id, the counts, base_failed, good_probability and kept."""
    counts = save(with_counts(docs.select("doc_id", "text")).select("doc_id", *COUNTS), "quality-counts")
    patterns = vote_patterns(counts, rules)
    failed = F.expr(Rule._on(BASE_FAILED, ""))
    good = fit(patterns).posterior([r.vote() for r in rules], patterns)
    return counts.select("doc_id", *COUNTS, failed.alias("base_failed"), good.alias("good_probability"), (~failed & (good >= threshold)).alias("kept"))


def keep_good(docs: DataFrame, rules: tuple[Rule, ...] = RULES, threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs`` that are kept, with their columns as they are.

    Counts are worked out twice, which needs no join and no copy of the texts.
    """
    p = "_quality_"
    # The row number keeps the optimiser from working the counts out anew for every condition on them;
    # a filter on it keeps it from being left out.
    counted = with_counts(docs, p).withColumn(f"{p}row", F.monotonically_increasing_id()).filter(F.col(f"{p}row") >= 0)
    patterns = vote_patterns(counted, rules, p)
    good = fit(patterns).posterior([r.vote(p) for r in rules], patterns) >= threshold
    return counted.filter(~F.expr(Rule._on(BASE_FAILED, p)) & good).select(*docs.columns)


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(documents(spark, sf_dir)).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "good_probability")
