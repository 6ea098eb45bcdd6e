"""Fingerprints by consistent weighted sampling.

A document is a bag of words with their counts as weights.  For sample ``k`` and
word ``w`` three numbers are drawn from a hash of both: two gamma(2, 1) variates
``r`` and ``c`` and a uniform ``b``.  With ``t = floor(ln(weight) / r + b)``, the
word with the least ``ln c - r * (t - b + 1)`` is the sample, together with its
``t``.  Two documents share a sample with the probability of their generalised
Jaccard similarity, the sum of the lesser weights over that of the greater ones.

A gamma(2, 1) variate is minus the logarithm of the product of two uniform ones,
which are 13 bits each of one 64-bit hash (12 for ``b``).  Everything is DataFrame
expressions: a text's words are sorted by their 64-bit hash in the row, where equal
neighbours are counted, and the samples are minima of 64-bit numbers that an
aggregation combines, some of them in each of its rows.  The likeness of two
texts is in steps of one in ``SAMPLES``, with a standard error of at most 0.0625
at 64 samples.

Null texts count as empty; a text without words has the fingerprint of no
samples, which is like itself only.  Equal texts have equal fingerprints.  Rows
with equal doc_id are followed by each other in the order of their text, equal
rows in any order, each with a result of its own; rows without doc_id are followed
by themselves.  A very long text is one row of words at a time; other columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dgprop.llm.common import SPACES, WORD_GAP, documents, parts_for, text_rows

SAMPLES = 64
#: Samples that one aggregation row holds; more take several rows for each text.
PER_ROW = 16
#: Rows of one bucket of the order by doc_id, about.
BUCKET_ROWS = 2_000
#: Ranges of doc_id that are found by quantiles; each is cut evenly further.
MOST_RANGES = 200
#: Rows of three numbers that are broadcast at most; beyond it they are shuffled.
MOST_BROADCAST = 200_000


def _uniform(bits: Column, first: int, n: int) -> Column:
    """The middle of one of ``2 ** n`` steps between 0 and 1, from ``n`` of the 64 bits."""
    return (F.shiftrightunsigned(bits, first).bitwiseAND(F.lit((1 << n) - 1)) + 0.5) * (0.5**n)


def with_bag(rows: DataFrame) -> DataFrame:
    """Add ``bag``: the hash and the count of each word of the text; without words it is null."""
    bare = F.btrim("text", F.lit(SPACES))
    words = F.when(bare != "", F.split(bare, WORD_GAP))
    rows = rows.withColumn("sorted", F.sort_array(F.transform(words, lambda w: F.xxhash64(w))))
    before = F.concat(F.array(F.lit(None).cast("bigint")), F.slice("sorted", 1, F.size("sorted") - 1))
    marked = F.zip_with(before, F.col("sorted"), lambda a, b: F.struct(b.alias("h"), (~a.eqNullSafe(b)).alias("first")))
    firsts = F.filter(F.transform(marked, lambda x, i: F.struct(x["h"].alias("h"), x["first"].alias("first"), i.alias("i"))), lambda x: x["first"])
    rows = rows.withColumn("firsts", firsts)
    ends = F.concat(F.slice(F.transform("firsts", lambda x: x["i"]), 2, F.size("firsts") - 1), F.array(F.size("sorted")))
    bag = F.zip_with(F.col("firsts"), ends, lambda x, end: F.struct(x["h"].alias("term"), (end - x["i"]).alias("n")))
    return rows.withColumn("bag", F.when(F.size("sorted") > 0, bag)).drop("sorted", "firsts")


def signatures(rows: DataFrame, keys: list[str], n_samples: int = SAMPLES) -> DataFrame:
    """From the keys and a text: the keys and the list of samples (null without words).

    The keys have to tell texts apart; the aggregation is by them.
    """
    parts = list(range(-(-n_samples // PER_ROW)))
    bags = with_bag(rows.select(*keys, "text")).select(*keys, "bag", F.explode(F.lit(parts)).alias("part"))
    terms = bags.select(*keys, "part", F.explode_outer("bag").alias("w"))
    terms = terms.select(*keys, "part", F.shiftrightunsigned("w.term", 32).alias("low"), F.log("w.n").alias("ln_weight"), F.xxhash64("w.term", "part").alias("drawn"))
    least = []
    for k in range(PER_ROW):
        bits = F.xxhash64(F.col("drawn").bitwiseXOR(F.lit(k).cast("bigint")))
        r = -F.log(_uniform(bits, 0, 13) * _uniform(bits, 13, 13))
        ln_c = F.log(-F.log(_uniform(bits, 26, 13) * _uniform(bits, 39, 13)))
        b = _uniform(bits, 52, 12)
        t = F.floor(F.col("ln_weight") / r + b)
        rank = ln_c - r * (t - b + 1)
        # The rank to 2 ** -22 in the upper half, the drawn (term, t) in the lower one.
        key = F.shiftleft(F.greatest(F.least(F.floor(rank * (1 << 22)), F.lit((1 << 31) - 1)), F.lit(-(1 << 31))), 32)
        least.append(F.min(key.bitwiseOR(F.col("low").bitwiseXOR(t.bitwiseAND(F.lit(0xFFFFFFFF))))).alias(f"s{k}"))
    # The rank is of no use once the least is found: what was drawn is kept as a 32-bit number.
    drawn = [F.shiftright(F.shiftleft(f"s{k}", 32), 32).cast("int") for k in range(PER_ROW)]
    found = terms.groupBy(*keys, "part").agg(*least).select(*keys, "part", F.when(F.col("s0").isNotNull(), F.array(*drawn)).alias("some"))
    whole = F.concat(*[F.max(F.when(F.col("part") == i, F.col("some"))) for i in parts])
    return found.groupBy(*keys).agg(F.slice(whole, 1, n_samples).alias("samples"))


def fingerprint(samples: Column) -> Column:
    """Eight hexadecimal digits for each sample; no samples: the empty string."""
    part = F.transform(samples, lambda s: F.lpad(F.lower(F.hex(s.bitwiseAND(F.lit(0xFFFFFFFF)))), 8, "0"))
    return F.coalesce(F.array_join(part, ""), F.lit(""))


def likeness(a: Column, b: Column, n_samples: int = SAMPLES) -> Column:
    """Share of equal samples of two fingerprints' sample lists; two without samples are alike."""
    same = F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda x: x))
    return F.when(a.isNull() & b.isNull(), 1.0).when(a.isNull() | b.isNull(), 0.0).otherwise(same / n_samples)


def with_next(docs: DataFrame, ghosts_too: bool = False) -> DataFrame:
    """Add next_text, next_id, bucket, place and ghost (1 for rows that stand for the next bucket's first, left out by default): the next document in descending doc_id, after the last the first.

    Rows without doc_id are followed by themselves (in buckets below 0).  Bucket and
    place are one row's only.  Rows are put in buckets that are ranges of doc_id, so that no task orders the
    whole table; each bucket also gets the row that follows it, the first of the
    bucket below.
    """
    own = docs.filter(F.col("doc_id").isNull())
    alone = (-1 - F.pmod(F.xxhash64("text"), F.lit(1 << 20))).alias("bucket")
    own = own.select("doc_id", "text", F.col("doc_id").alias("next_id"), F.col("text").alias("next_text"), alone, F.monotonically_increasing_id().alias("place"), F.lit(0).alias("ghost"))
    docs = docs.filter(F.col("doc_id").isNotNull())
    n = docs.count()
    if n == 0:
        return own
    n_ranges = min(MOST_RANGES, parts_for(n, BUCKET_ROWS))
    cuts = docs.select(F.percentile_approx("doc_id", [i / n_ranges for i in range(n_ranges + 1)], 20 * MOST_RANGES)).head()[0]
    low, high = docs.agg(F.min("doc_id"), F.max("doc_id")).head()
    cuts = sorted({low, *cuts[1:-1]})
    each = parts_for(n, BUCKET_ROWS * n_ranges)
    bounds, ends = F.array(*[F.lit(c).cast("bigint") for c in cuts]), F.array(*[F.lit(c).cast("bigint") for c in [*cuts[1:], high + 1]])
    at = F.size(F.filter(bounds, lambda b: b <= F.col("doc_id"))) - 1
    start, end = F.get(bounds, at), F.get(ends, at)
    within = F.floor((F.col("doc_id") - start) / (end - start).cast("double") * each) if each > 1 else F.lit(0)
    placed = docs.withColumn("bucket", (at * each + within).cast("bigint"))
    heads = placed.groupBy("bucket").agg(F.max("doc_id").alias("head_id"))
    order = [r["bucket"] for r in heads.orderBy("bucket").collect()] if each == 1 else None
    if order is not None:
        above = {b: order[i + 1] if i + 1 < len(order) else order[0] for i, b in enumerate(order)}
        goes_to = F.element_at(F.create_map(*[F.lit(x).cast("bigint") for p in above.items() for x in p]), F.col("bucket"))
        heads = heads.select(F.col("head_id").alias("doc_id"), F.col("bucket").alias("own"), goes_to.alias("bucket"))
    else:
        # The bucket above is the next one in use; the last one's head goes to the first.
        ring = heads.withColumn("range", F.floor(F.col("bucket") / each))
        inner = Window.partitionBy("range").orderBy("bucket")
        firsts = ring.groupBy("range").agg(F.min("bucket").alias("first"))
        firsts = firsts.withColumn("after", F.coalesce(F.lead("first").over(Window.orderBy("range")), F.lit(None)))
        lowest = heads.agg(F.min("bucket")).head()[0]
        ring = ring.withColumn("up", F.lead("bucket").over(inner)).join(F.broadcast(firsts.select("range", "after")), "range")
        heads = ring.select(F.col("head_id").alias("doc_id"), F.col("bucket").alias("own"), F.coalesce("up", "after", F.lit(lowest)).alias("bucket"))
    # One text follows each bucket; of equal ids the first in the order below.
    n_heads = heads.count()
    few = F.broadcast(heads) if n_heads <= MOST_BROADCAST else heads
    tops = placed.withColumnRenamed("bucket", "own").join(few, ["doc_id", "own"]).groupBy("bucket", "doc_id").agg(F.max("text").alias("text"))
    ghosts = tops.select("doc_id", "text", "bucket", F.lit(1).alias("ghost"))
    # Rows without doc_id go through the same window, so that all rows lie by bucket after it.
    ring = placed.select("doc_id", "text", "bucket", F.lit(0).alias("ghost")).unionByName(ghosts).unionByName(own.select("doc_id", "text", "bucket", "ghost"))
    down = Window.partitionBy("bucket").orderBy("ghost", F.desc("doc_id"), F.desc("text"))
    following = F.when(F.col("doc_id").isNull(), F.col("text")).otherwise(F.lead("text").over(down))
    followed = ring.withColumns({"next_id": F.when(F.col("doc_id").isNotNull(), F.lead("doc_id").over(down)), "next_text": following, "place": F.row_number().over(down).cast("bigint")})
    return (followed if ghosts_too else followed.filter(F.col("ghost") == 0)).select("doc_id", "text", "next_id", "next_text", "bucket", "place", "ghost")


def op4_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    half = F.floor(F.length("text") / 2).cast("int")
    kept = F.substring(F.col("text"), F.lit(1), F.length("text") - half)
    edited = F.concat(kept, F.substring(F.col("next_text"), F.lit(1), half))
    # The rows lie by bucket; with it among the keys nothing more is shuffled, and the next document's samples stand in the next place.
    key = ["bucket", "place", "doc_id", "ghost", "n_chars"]
    rows = with_next(text_rows(documents(spark, sf_dir)), ghosts_too=True).select("bucket", "place", "doc_id", "ghost", F.length("text").cast("bigint").alias("n_chars"), "text", edited.alias("edited"))
    sides = F.array(F.struct(F.col("text"), F.lit("").alias("edited_sha256")), F.struct(F.col("edited").alias("text"), F.sha2("edited", 256).alias("edited_sha256")))
    rows = rows.select(*key, F.explode(F.when(F.col("ghost") == 0, sides).otherwise(F.slice(sides, 1, 1))).alias("s")).select(*key, "s.*")
    made = signatures(rows, [*key, "edited_sha256"])
    is_own = F.col("edited_sha256") == ""
    both = made.groupBy(*key).agg(F.max("edited_sha256").alias("edited_sha256"), F.max(F.when(is_own, F.col("samples"))).alias("a"), F.max(F.when(~is_own, F.col("samples"))).alias("b"))
    after = F.lead("a").over(Window.partitionBy("bucket").orderBy("place"))
    both = both.withColumn("c", F.when(F.col("doc_id").isNull(), F.col("a")).otherwise(after)).filter("ghost = 0")
    return both.select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        fingerprint(F.col("a")).alias("fingerprint"),
        fingerprint(F.col("b")).alias("edited_fingerprint"),
        likeness(F.col("a"), F.col("b")).alias("near_edited"),
        likeness(F.col("a"), F.col("c")).alias("near_next"),
    )
