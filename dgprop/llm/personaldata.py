"""Personal data by candidates and gradient-boosted trees, in DataFrame expressions.

Strict patterns with their checks (Luhn's sum, parts of at most 255, numbers of
digits) give the base spans, which always stay.  Looser generators of high recall
propose more spans, which may overlap: addresses written out, numbers with other
separators or without a prefix.  Each candidate has features of its format and its
context, all in small bins.  Boosted trees of depth two are grown from the counts
of equal feature vectors (their number is bounded by the bins, whatever the
input).  Positives are base spans in an altered form that a loose pattern matches,
in the place where they stand; negatives are strict matches that fail their check,
and loose ones over a base span of another kind.  Candidates that the trees decide
on are in neither.  The threshold of each kind is as low as the precision on the
held-out half of the labelled texts allows, and not below even chances.

Positions are code points, ends exclusive: running sums of the matches and the
gaps between them, in windows over the matches of one text, which are rows.
Overlaps come from running ends in the order of starts.  So the work for a text
grows with its length times the logarithm of its matches, a very long text of
numbers included.  Equal texts are worked on once.  Null and empty texts have no
span; repeated rows are treated alike; texts are told apart by 128 bits of hash;
other columns are passed on by ``redact`` (those that start with ``_text`` and
``_cuts`` must not be there) and ignored by ``find_spans``; without candidates of a kind, in
an empty table too, nothing is added.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dgprop.llm.common import documents, save

KINDS = ("email", "ip", "card", "phone")
# What a base span of each kind is. Possessive where nothing can be given back,
# and starting only where a match can start, which finds the same spans without repeated scans.
BASE = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Candidates beyond the base spans.
LOOSE = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}(?:\x20?(?:\(at\)|\[at\]|\{at\}|@)\x20?[A-Za-z0-9-]{1,63}(?:(?:\.|\x20?(?:\(dot\)|\[dot\]|\{dot\})\x20?)[A-Za-z0-9-]{1,63}){1,4}|\x20at\x20[A-Za-z0-9-]{1,63}(?:\x20dot\x20[A-Za-z0-9-]{1,63}){1,4})",
    "ip": r"(?<![0-9.])[0-9]{1,3}(?:\x20?(?:\.|\[\.\]|\(\.\))\x20?[0-9]{1,3}){3}(?![0-9.])",
    "card": r"(?<![0-9])[0-9]{2,6}(?:[\x20._/-]{1,2}[0-9]{2,6}){2,7}(?![0-9])",
    "phone": r"(?<![0-9+])(?:00|\(0\)|\()?[0-9]{2,4}\)?[\x20./-]{1,2}[0-9]{2,4}(?:[\x20./-]{1,2}[0-9]{2,5}){1,3}(?![0-9])",
}
#: What a text must hold for a pattern to be worth trying.
HINTS = {"email": r"@|[(\[{\x20]at[)\]}\x20]", "ip": r"[0-9]", "card": r"[0-9]", "phone": r"[0-9]"}
#: Code points before and after a match that make its context.
NEAR = 30
CUES = "mail|contact|phone|tel|call|mobile|fax|card|visa|credit|ip|address|server|host|login|account"
#: Upper bounds of the bins of each feature.
BINS = {
    "kind": (0, 1, 2),
    "size": (8, 11, 14, 17, 20, 30),
    "digits": (0, 5, 9, 12, 13, 15, 16, 19),
    "groups": (1, 2, 3, 4, 5),
    "passes": (0,),
    "left": (0, 1, 2),
    "right": (0, 1, 2),
    "cue": (0,),
    "near_digits": (0, 3, 8),
    "parts": (0, 1, 2),
}
FEATURES = tuple(BINS)
LEAST_PRECISION = 0.9
TEXT = ("text1", "text2")
_WRITTEN = "at|dot"


def text_keys(text: Column) -> list[Column]:
    """Two 64-bit hashes that tell texts apart."""
    return [F.xxhash64(text).alias(TEXT[0]), F.xxhash64(F.lit(1), text).alias(TEXT[1])]


def _sql(pattern: str) -> str:
    return "r'" + pattern.replace("'", "\\x27") + "'"


def _found(kind: int, pattern: str, base: bool) -> str:
    """SQL for all matches of a pattern, each with the gap before it, and one more entry for the last gap."""
    split, match = f"split(_text, {_sql(pattern)})", f"regexp_extract_all(_text, {_sql(pattern)}, 0)"
    made = f"zip_with({split}, {match}, (gap, m) -> struct({kind} AS kind, {str(base).lower()} AS base, length(gap) AS gap, right(gap, {NEAR}) AS before, left(gap, {NEAR}) AS head, m AS value))"
    none = f"filter(array(struct({kind} AS kind, true AS base, 0 AS gap, '' AS before, '' AS head, '' AS value)), x -> false)"
    return f"CASE WHEN _text RLIKE {_sql(HINTS[KINDS[kind]])} THEN filter({made}, (x, i) -> i > 0 OR x.value IS NOT NULL) ELSE {none} END"


def matches(docs: DataFrame) -> DataFrame:
    """The text's keys, kind, base, start, end, value, before and after: all matches of the strict and loose patterns, once for equal texts.

    A match's place is the running sum of the gaps and matches before it.
    """
    found = [_found(k, BASE[n], True) for k, n in enumerate(KINDS)] + [_found(k, LOOSE[n], False) for k, n in enumerate(KINDS)]
    rows = docs.select(F.coalesce("text", F.lit("")).alias("_text")).filter(" OR ".join(f"_text RLIKE {_sql(HINTS[k])}" for k in ("email", "ip")))
    rows = rows.select(*text_keys(F.col("_text")), F.array(*[F.expr(f) for f in found]).alias("_all"))
    one = rows.select(*TEXT, F.explode("_all").alias("_kind")).select(*TEXT, F.posexplode("_kind").alias("k", "m")).select(*TEXT, "k", "m.*")
    one = one.dropDuplicates([*TEXT, "kind", "base", "k"])
    along = Window.partitionBy(*TEXT, "kind", "base").orderBy("k")
    size = F.length("value")
    placed = one.withColumns({"end": F.sum(F.col("gap") + F.coalesce(size, F.lit(0))).over(along), "after": F.lead("head").over(along)}).filter("value IS NOT NULL")
    return placed.select(*TEXT, "kind", "base", (F.col("end") - size).cast("int").alias("start"), F.col("end").cast("int").alias("end"), "value", "before", "after")


_DIGITS = "regexp_replace({v}, '[^0-9]', '')"
_LUHN = """aggregate(filter(split(reverse({d}), ''), p -> p <> ''), struct(0 AS sum, 0 AS i),
    (had, p) -> struct(had.sum + CASE WHEN had.i % 2 = 0 THEN CAST(p AS int) WHEN CAST(p AS int) > 4 THEN 2 * CAST(p AS int) - 9 ELSE 2 * CAST(p AS int) END AS sum, had.i + 1 AS i),
    had -> had.sum % 10 = 0)"""


def _passes(v: str, strict: str) -> str:
    """SQL for whether a value passes the check of its kind."""
    d = _DIGITS.format(v=v)
    return f"""CASE kind
        WHEN 0 THEN {strict} OR {v} RLIKE '[A-Za-z]{{2,}}$'
        WHEN 1 THEN forall(filter(split(regexp_replace({v}, '[^0-9.]', ''), '[.]'), p -> p <> ''), p -> length(ltrim('0', p)) <= 3 AND coalesce(try_cast(ltrim('0', p) AS int), 0) <= 255)
        WHEN 2 THEN CASE WHEN length({d}) BETWEEN 14 AND 19 THEN {_LUHN.format(d=d)} ELSE false END
        ELSE length({d}) BETWEEN 10 AND 15 END"""


def _char_class(char: str) -> str:
    return f"CASE WHEN {char} = '' OR {char} RLIKE '\\\\s' THEN 0 WHEN {char} RLIKE '[0-9]' THEN 2 WHEN {char} RLIKE '\\\\p{{L}}' THEN 3 ELSE 1 END"


def _bin(value: str, bounds: tuple[int, ...]) -> str:
    return "CASE " + " ".join(f"WHEN {value} <= {b} THEN {i}" for i, b in enumerate(bounds)) + f" ELSE {len(bounds)} END"


def _features(v: str, passes: str) -> Column:
    """The bins of a value's format and of what stands before and after it."""
    value = {
        "kind": "kind",
        "size": f"length({v})",
        "digits": f"length({_DIGITS.format(v=v)})",
        "groups": f"size(regexp_extract_all({v}, '[0-9]+', 0))",
        "parts": f"CASE WHEN {v} RLIKE '[(\\\\[{{]| ({_WRITTEN}) ' THEN 3 WHEN {v} RLIKE '[/_-]' THEN 2 WHEN {v} RLIKE '[.]' THEN 1 ELSE 0 END",
        "passes": f"CAST({passes} AS int)",
        "left": _char_class("right(before, 1)"),
        "right": _char_class("left(after, 1)"),
        "cue": f"CAST(lower(before) RLIKE '\\\\b({CUES})' AS int)",
        "near_digits": "length(regexp_replace(concat(before, after), '[^0-9]', ''))",
    }
    return F.expr("array(" + ", ".join(f"CAST({_bin(value[f], BINS[f])} AS int)" for f in FEATURES) + ")")


def _altered() -> str:
    """SQL for a base span as people write it to be found less easily: other separators, written-out signs, no prefix."""
    turn = "pmod(xxhash64(text1, start), 3)"
    digits = _DIGITS.format(v="value")
    name, host, own = "substring_index(value, '@', 1)", "substring_index(value, '@', -1)", "regexp_replace(value, '^[+][0-9]{1,3}[ .-]*', '')"
    return f"""CASE kind
        WHEN 0 THEN CASE {turn} WHEN 0 THEN concat({name}, ' (at) ', replace({host}, '.', ' (dot) ')) WHEN 1 THEN concat({name}, ' at ', replace({host}, '.', ' dot ')) ELSE concat({name}, '[at]', {host}) END
        WHEN 1 THEN CASE {turn} WHEN 0 THEN replace(value, '.', '[.]') WHEN 1 THEN replace(value, '.', ' . ') ELSE replace(value, '.', '(.)') END
        WHEN 2 THEN regexp_replace({digits}, '(....)(?=.)', CASE {turn} WHEN 0 THEN '$1.' WHEN 1 THEN '$1/' ELSE '$1_' END)
        ELSE CASE {turn} WHEN 0 THEN concat('00', regexp_replace(substring(value, 2), '[^0-9]+', ' ')) WHEN 1 THEN {own} ELSE replace(trim(regexp_replace({own}, '[^0-9]+', ' ')), ' ', '.') END END"""


def candidates(docs: DataFrame) -> DataFrame:
    """The text's keys, kind, start, end, state, x: valid base spans (state 1), undecided candidates (-1) and known negatives (0).

    A base span's features are those of an altered form of it (null if no loose
    pattern matches that).  Strict matches that fail their check, and loose ones that
    lie over a base span of another kind only, are no personal data of their kind;
    loose ones over a base span of their own kind are that span and are left out.
    """
    rows = matches(docs).withColumn("passes", F.expr(_passes("value", "base")))
    held = F.col("base") & F.col("passes")
    up, down = (Window.partitionBy(*TEXT).orderBy(*o).rowsBetween(Window.unboundedPreceding, -1) for o in ((F.col("start"), F.desc("base"), F.col("kind")), (F.desc("start"), F.col("base"), F.desc("kind"))))
    over = F.lit(False)
    own = F.lit(False)
    for k in range(len(KINDS)):
        mine = held & (F.col("kind") == k)
        rows = rows.withColumns({f"_e{k}": F.max(F.when(mine, F.col("end"))).over(up), f"_s{k}": F.min(F.when(mine, F.col("start"))).over(down)})
        meets = F.coalesce(F.col(f"_e{k}") > F.col("start"), F.lit(False)) | F.coalesce(F.col(f"_s{k}") < F.col("end"), F.lit(False))
        over, own = over | meets, own | (meets & (F.col("kind") == k))
    state = F.when(held, 1).when(F.col("base"), 0).when(own, None).when(over, 0).otherwise(-1)
    rows = rows.withColumn("state", state).filter("state IS NOT NULL").withColumn("form", F.when(held, F.expr(_altered())).otherwise(F.col("value")))
    matched = "CASE kind " + " ".join(f"WHEN {k} THEN regexp_extract(form, {_sql(LOOSE[n])}, 0) = form" for k, n in enumerate(KINDS)) + " END"
    x = F.when((F.col("state") < 1) | F.expr(matched), _features("form", _passes("form", "false")))
    return rows.select(*TEXT, "kind", "start", "end", "state", x.alias("x"))


@dataclass(frozen=True)
class Tree:
    """A leaf's value, or a feature, the greatest bin that goes left, and two trees."""

    value: float = 0.0
    feature: int = -1
    most: int = 0
    left: Tree | None = None
    right: Tree | None = None

    def score(self, x: tuple[int, ...]) -> float:
        if self.feature < 0:
            return self.value
        return (self.left if x[self.feature] <= self.most else self.right).score(x)

    def sql(self, x: str) -> str:
        if self.feature < 0:
            return f"{self.value!r}D"
        return f"CASE WHEN {x}[{self.feature}] <= {self.most} THEN {self.left.sql(x)} ELSE {self.right.sql(x)} END"


@dataclass
class CandidateModel:
    """Boosted trees, and the least score of each kind."""

    start: float = 0.0
    trees: list[Tree] = field(default_factory=list)
    thresholds: list[float] = field(default_factory=lambda: [math.inf] * len(KINDS))

    def score(self, x: tuple[int, ...]) -> float:
        return self.start + sum(t.score(x) for t in self.trees)

    def sql(self, x: str) -> str:
        return " + ".join([f"{self.start!r}D", *(f"({t.sql(x)})" for t in self.trees)])

    def limit(self) -> str:
        """SQL for the least score of a candidate's kind."""
        known = " ".join(f"WHEN {k} THEN {t!r}D" for k, t in enumerate(self.thresholds) if t < math.inf)
        return f"CASE kind {known} ELSE 1e300D END" if known else "1e300D"


def _grow(rows: list[tuple[tuple[int, ...], float, float]], depth: int, least: float, damp: float) -> Tree:
    """A tree on (x, gradient, curvature) by the gain of Newton's steps."""
    g, h = sum(r[1] for r in rows), sum(r[2] for r in rows)
    leaf = Tree(-g / (h + damp))
    if depth == 0:
        return leaf
    best, where = 1e-9, None
    for f, name in enumerate(FEATURES[: len(rows[0][0])]):
        sums = [[0.0, 0.0] for _ in range(len(BINS[name]) + 1)]
        for x, gx, hx in rows:
            sums[x[f]][0] += gx
            sums[x[f]][1] += hx
        gl = hl = 0.0
        for most in range(len(sums) - 1):
            gl, hl = gl + sums[most][0], hl + sums[most][1]
            if hl >= least and h - hl >= least:
                gain = gl * gl / (hl + damp) + (g - gl) ** 2 / (h - hl + damp) - g * g / (h + damp)
                if gain > best:
                    best, where = gain, (f, most)
    if where is None:
        return leaf
    f, most = where
    left, right = [r for r in rows if r[0][f] <= most], [r for r in rows if r[0][f] > most]
    return Tree(0.0, f, most, _grow(left, depth - 1, least, damp), _grow(right, depth - 1, least, damp))


def boost(counts: list[tuple[tuple[int, ...], int, int, int]], n_trees: int = 40, rate: float = 0.3, depth: int = 2, least: float = 1.0, damp: float = 1.0) -> CandidateModel:
    """From (x, label, fold, number): trees from fold 0, thresholds from fold 1."""
    model = CandidateModel()
    table: dict[tuple[int, ...], list[float]] = {}
    for x, label, fold, n in sorted(counts):
        if fold == 0 and label >= 0:
            table.setdefault(x, [0.0, 0.0])[label] += n
    positive, total = sum(t[1] for t in table.values()), sum(sum(t) for t in table.values())
    if not positive or positive == total:
        return model
    model.start = math.log(positive / (total - positive))
    margin = dict.fromkeys(table, model.start)
    for _ in range(n_trees):
        rows = []
        for x, (neg, pos) in table.items():
            p = 1 / (1 + math.exp(-max(-30.0, min(30.0, margin[x]))))
            rows.append((x, (neg + pos) * p - pos, (neg + pos) * p * (1 - p)))
        tree = _scaled(_grow(rows, depth, least, damp), rate)
        model.trees.append(tree)
        for x in margin:
            margin[x] += tree.score(x)
    for kind in range(len(KINDS)):
        held = sorted(((model.score(x), label, n) for x, label, fold, n in counts if fold == 1 and label >= 0 and x[0] == kind), reverse=True)
        right = seen = 0
        for i, (score, label, n) in enumerate(held):
            right, seen = right + n * label, seen + n
            below = held[i + 1][0] if i + 1 < len(held) else 0.0
            if score > 0 and right >= LEAST_PRECISION * seen and below < score:
                # Nothing is known to be wrong above the next score below.
                model.thresholds[kind] = max(below, 0.0) + 1e-9
    return model


def _scaled(tree: Tree, rate: float) -> Tree:
    if tree.feature < 0:
        return Tree(tree.value * rate)
    return Tree(0.0, tree.feature, tree.most, _scaled(tree.left, rate), _scaled(tree.right, rate))


def fit(found: DataFrame) -> CandidateModel:
    """Fit on candidates; what is collected are counts of feature vectors."""
    fold = F.pmod(F.xxhash64(*TEXT), F.lit(2)).cast("int")
    rows = found.filter("state >= 0 AND x IS NOT NULL").groupBy("x", "state", fold.alias("fold")).count().collect()
    return boost([(tuple(r["x"]), r["state"], r["fold"], r["count"]) for r in rows])


def spans_of(found: DataFrame, model: CandidateModel) -> DataFrame:
    """For each text with spans its keys, ``base`` and ``spans``, (start, kind, end) in order, and ``cuts``, which don't overlap.

    Of accepted candidates that overlap in a chain the best one is added.  A cut
    is a chain of overlapping spans and has the kind of the first.
    """
    kept = found.filter("state <> 0").withColumn("score", F.when(F.col("state") == 1, F.lit(math.inf)).otherwise(F.expr(model.sql("x"))))
    kept = kept.filter(f"state = 1 OR score >= {model.limit()}")

    def chained(rows: DataFrame, *group: str) -> DataFrame:
        along = Window.partitionBy(*TEXT, *group).orderBy("start", "end", "kind")
        new = F.coalesce(F.max("end").over(along.rowsBetween(Window.unboundedPreceding, -1)) <= F.col("start"), F.lit(True))
        return rows.withColumn("_new", new.cast("int")).withColumn("_chain", F.sum("_new").over(along))

    best = Window.partitionBy(*TEXT, "state", "_chain").orderBy(F.desc("score"), "start", "kind")
    one = chained(kept, "state").withColumn("_rank", F.row_number().over(best)).filter("state = 1 OR _rank = 1")
    span = F.struct("start", "kind", "end")
    cuts = chained(one).groupBy(*TEXT, "_chain").agg(F.min("start").alias("start"), F.min(F.struct("start", "end", "kind"))["kind"].alias("kind"), F.max("end").alias("end"), F.collect_list(F.when(F.col("state") == 1, span)).alias("base"), F.collect_list(span).alias("spans"))
    listed = [F.array_sort(F.flatten(F.collect_list(c))).alias(c) for c in ("base", "spans")]
    return cuts.groupBy(*TEXT).agg(*listed, F.array_sort(F.collect_list(span)).alias("cuts"))


def _listed(spans: str) -> Column:
    names = "array(" + ", ".join(f"'{k}'" for k in KINDS) + ")"
    return F.expr(f"array_join(transform({spans}, s -> concat({names}[s.kind], ':', s.start, ':', s.end)), ',')")


def found_spans(docs: DataFrame) -> DataFrame:
    found = save(candidates(docs), "candidates")
    return spans_of(found, fit(found))


def find_spans(docs: DataFrame) -> DataFrame:
    """doc_id, the numbers of base spans, base_spans and spans as text, base_sha256 and n_added."""
    rows = docs.select("doc_id", *text_keys(F.coalesce("text", F.lit(""))))
    spans = rows.join(found_spans(docs), list(TEXT), "left")
    none = F.expr("CAST(array() AS array<struct<start:int,kind:int,end:int>>)")
    spans = spans.withColumns({c: F.coalesce(c, none) for c in ("base", "spans")})
    # As SQL: of a Python function with a second parameter Spark would make the place in the array that one.
    counts = [F.expr(f"CAST(size(filter(base, s -> s.kind = {k})) AS bigint)").alias(f"n_{n}") for k, n in enumerate(KINDS)]
    return spans.select("doc_id", *counts, _listed("base").alias("base_spans"), F.sha2(_listed("base"), 256).alias("base_sha256"), _listed("spans").alias("spans"), (F.size("spans") - F.size("base")).alias("n_added"))


def redact(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` with every span of the text replaced by its kind in angle brackets; n_chars follows, where it is there.

    Of overlapping spans the one that starts first is replaced, to the end of the last of them.
    """
    keys = [f"_{t}" for t in TEXT]
    cuts = found_spans(docs).select(*[F.col(t).alias(k) for t, k in zip(TEXT, keys, strict=True)], F.col("cuts").alias("_cuts"))
    rows = docs.withColumns(dict(zip(keys, text_keys(F.coalesce("text", F.lit(""))), strict=True))).join(cuts, keys, "left")
    # For each code point: 0 stays, -1 goes, k + 1 gives way to the name of kind k.
    marks = """flatten(zip_with(_cuts, concat(array(0), transform(_cuts, s -> s.end)), (s, had) ->
        CASE WHEN s IS NULL THEN array_repeat(0, length(text) - had) ELSE concat(array_repeat(0, s.start - had), array(s.kind + 1), array_repeat(-1, s.end - s.start - 1)) END))"""
    names = "array(" + ", ".join(f"'<{k.upper()}>'" for k in KINDS) + ")"
    replaced = f"array_join(zip_with(split(text, ''), {marks}, (c, m) -> CASE WHEN m = 0 THEN c WHEN m = -1 THEN '' ELSE {names}[m - 1] END), '')"
    some = F.col("_cuts").isNotNull()
    done = rows.withColumn("text", F.when(some, F.expr(replaced)).otherwise(F.col("text")))
    if "n_chars" in docs.columns:
        done = done.withColumn("n_chars", F.when(some, F.length("text")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType))
    return done.select(*docs.columns)


def op6_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_spans(documents(spark, sf_dir))
    return found.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_added")
