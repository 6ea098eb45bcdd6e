"""Graph events, edges, features and labels from the given tables.

Ids of different kinds have ranges of their own: ``kind * 10**12 + key``.
Timestamps are handed on as microseconds since 1970, so that engines agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.functions.hashing import uniform

KIND = 10**12
USER, ITEM, CUSTOMER, PART, SUPPLIER, DOCUMENT, LINE, PAGE, LINK, VECTOR, UTTERANCE = (i * KIND for i in range(1, 12))
DAY_US = 86_400_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(ts: str) -> Column:
    """Microseconds since 1970 of a timestamp without zone."""
    # As a difference of local times: the session's zone has no part in it.
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', {ts})")


def interactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User and item of every event: seq, ts_us, kind, src, dst, w, event_type, value."""
    e = table(spark, sf_dir, "events")
    return e.select(
        F.col("event_id").alias("seq"),
        micros("ts").alias("ts_us"),
        F.lit("add_edge").alias("kind"),
        (F.col("user_id") + USER).alias("src"),
        (F.get_json_object("props", "$.k").cast("bigint") + ITEM).alias("dst"),
        F.lit(1.0).alias("w"),
        "event_type",
        "value",
    )


def trades(spark: SparkSession, sf_dir: str, to: str = "part") -> DataFrame:
    """Customer and part (or supplier) of every line of an order, at the order's date."""
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    other = F.col("l_partkey") + PART if to == "part" else F.col("l_suppkey") + SUPPLIER
    return o.join(li, o.o_orderkey == li.l_orderkey).select(
        (F.col("l_orderkey") * 10 + F.col("l_linenumber")).alias("seq"),
        micros("o_orderdate").alias("ts_us"),
        F.lit("add_edge").alias("kind"),
        (F.col("o_custkey") + CUSTOMER).alias("src"),
        other.alias("dst"),
        F.lit(1.0).alias("w"),
        "l_discount",
        "l_returnflag",
        "o_orderstatus",
        micros("l_shipdate").alias("ship_us"),
    )


def trades_with_returns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer and supplier of finished orders; a returned line deletes its edge a day after the later of order and shipping."""
    adds = trades(spark, sf_dir, "supplier").filter("o_orderstatus = 'F'")
    back = adds.filter("l_returnflag = 'R'").select("seq", (F.greatest("ts_us", "ship_us") + DAY_US).alias("ts_us"), F.lit("del_edge").alias("kind"), "src", "dst", "w")
    return adds.select("seq", "ts_us", "kind", "src", "dst", "w").unionByName(back)


def with_expiry(events: DataFrame, days: int) -> DataFrame:
    """Every edge is deleted ``days`` after it was added."""
    columns = ["seq", "ts_us", "kind", "src", "dst", "w"]
    gone = events.select("seq", (F.col("ts_us") + days * DAY_US).alias("ts_us"), F.lit("del_edge").alias("kind"), "src", "dst", "w")
    return events.select(*columns).unionByName(gone)


def co_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier pairs inside one order, by the order's month: step, src < dst, w."""
    li, o = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    one = li.select("l_orderkey", (F.col("l_suppkey") + SUPPLIER).alias("src"))
    two = li.select("l_orderkey", (F.col("l_suppkey") + SUPPLIER).alias("dst"))
    month = (F.year("o_orderdate") * 12 + F.month("o_orderdate") - 1).alias("step")
    pairs = one.join(two, "l_orderkey").filter("src < dst")
    return pairs.join(o.select(F.col("o_orderkey").alias("l_orderkey"), month), "l_orderkey").groupBy("step", "src", "dst").agg(F.count("*").cast("double").alias("w"))


def shared_lines(spark: SparkSession, sf_dir: str, least: int = 20) -> DataFrame:
    """Documents and lines of more than ``least`` characters that several documents have, as src and dst."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).filter(F.length("line") > least)
    shared = lines.groupBy("line").agg(F.count("*").alias("n"), F.min("doc_id").alias("first")).filter("n > 1")
    # The line's id is a hash of it: no numbering of the whole table.
    line_id = F.conv(F.substring(F.md5("line"), 1, 9), 16, 10).cast("bigint") + LINE
    return lines.join(shared, "line").select((F.col("doc_id") + DOCUMENT).alias("src"), line_id.alias("dst"), F.lit(1.0).alias("w"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and their link targets, hashed to an id; w counts."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    target = F.conv(F.substring(F.md5("href"), 1, 9), 16, 10).cast("bigint") + LINK
    return pages.groupBy((F.col("page_id") + PAGE).alias("src"), target.alias("dst")).agg(F.count("*").cast("double").alias("w"))


def dialogue_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive turns of a conversation."""
    c = table(spark, sf_dir, "conversations")
    node = lambda t: F.col("conv_id") * 1000 + t + UTTERANCE
    nxt = c.select("conv_id", (F.col("turn") - 1).alias("turn"))
    return c.select("conv_id", "turn").join(nxt, ["conv_id", "turn"]).select(node(F.col("turn")).alias("src"), node(F.col("turn") + 1).alias("dst"), F.lit(1.0).alias("w"))


#: Vectors of one packed row: those that look for others, those that are looked through, and those that one product takes.
LOOKING, SEEN, AT_ONCE = 2_048, 16_384, 256
#: More than the rounding of a cosine and the error of a matrix product together.
_MARGIN = 3e-9
_PACKED = "u binary, e binary, n binary, least binary, width int"


def _packed(vectors: DataFrame, rows_each: int) -> DataFrame:
    """Rows of up to ``rows_each`` vectors as arrays; null vectors have a length of -1."""

    def work(batches):
        import numpy as np
        import pyarrow as pa

        def row(parts):
            t = pa.Table.from_batches(parts)
            u, n, least = (t.column(c).to_numpy() for c in ("u", "n", "least"))
            width = max((len(x) for x in t.column("e") if x.as_py() is not None), default=0)
            e = np.zeros((len(u), width))
            for i, x in enumerate(t.column("e").to_pylist()):
                if x is not None:
                    e[i] = x
            n = np.where([x is None for x in t.column("e").to_pylist()], -1.0, n)
            return pa.RecordBatch.from_pydict({**{c: pa.array([v.tobytes()], pa.binary()) for c, v in (("u", u), ("e", e), ("n", n), ("least", least))}, "width": pa.array([width], pa.int32())})

        held, size = [], 0
        for batch in batches:
            while batch.num_rows:
                part = batch.slice(0, rows_each - size)
                held, size, batch = [*held, part], size + part.num_rows, batch.slice(part.num_rows)
                if size == rows_each:
                    yield row(held)
                    held, size = [], 0
        if held:
            yield row(held)

    return vectors.select("u", "e", "n", "least").mapInArrow(work, _PACKED)


def _nearest_in_blocks(pairs: DataFrame, k: int) -> DataFrame:
    """Of each pair of packed rows, for each vector of the first those of the second that may be among the nearest: u, v, cos.

    A product of the blocks finds them; their cosines are summed up again in the order of the places.
    Undefined cosines are infinite, those of null vectors minus infinite; of equal ones as many are kept as can be told apart by ids.
    """

    def work(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for r in batch.to_pylist():
                (u, e, n, _), (v, f, m, least) = (
                    (np.frombuffer(r[s + "u"], np.int64), np.frombuffer(r[s + "e"]).reshape(-1, r[s + "width"]) if r[s + "width"] else np.zeros((len(r[s + "u"]) // 8, 0)), np.frombuffer(r[s + "n"]), np.frombuffer(r[s + "least"], np.int64)) for s in ("p", "q")
                )
                # The least ids first, so that a stable order keeps them among equals.
                order = np.argsort(least, kind="stable")
                v, f, m = v[order], f[order], m[order]
                width = max(e.shape[1], f.shape[1])
                e, f = (x if x.shape[1] == width else np.zeros((len(x), width)) for x in (e, f))
                odd = not (np.isfinite(e).all() and np.isfinite(f).all() and (n > 0).all() and (m > 0).all())
                with np.errstate(all="ignore"):
                    e1, f1 = e / n[:, None], (f / m[:, None]).T.copy()
                most = min(k + 1, len(v))
                each = max(1, min(64, len(v) // (8 * most)))
                starts = np.arange(0, len(v), each)
                for a in range(0, len(u), AT_ONCE):
                    c = e1[a : a + AT_ONCE] @ f1
                    if odd:
                        c[np.isnan(c)] = np.inf
                        c[(n[a : a + AT_ONCE] < 0)[:, None] | (m < 0)[None, :]] = -np.inf
                    # As many runs of places have a cosine of the bound or more as nearest ones are asked for.
                    runs = np.maximum.reduceat(c, starts, axis=1)
                    bound = np.partition(runs, runs.shape[1] - most, axis=1)[:, runs.shape[1] - most] if runs.shape[1] >= most else c.min(axis=1)
                    i, j = np.nonzero(c >= bound[:, None] - _MARGIN)
                    found = c[i, j]
                    for value in (np.inf, -np.inf) if odd else ():
                        same = found == value
                        turn = np.cumsum(same) - 1
                        first = np.searchsorted(i, i)
                        ahead = turn - np.where(first > 0, np.cumsum(same)[first - 1], 0)
                        keep = ~same | (ahead < most)
                        i, j, found = i[keep], j[keep], found[keep]
                    finite = np.flatnonzero(np.isfinite(found))
                    for z in range(0, len(finite), 65_536):
                        at = finite[z : z + 65_536]
                        x, y = i[at] + a, j[at]
                        found[at] = np.cumsum(e[x] * f[y], axis=1)[:, -1] / (n[x] * m[y])
                    yield pa.RecordBatch.from_arrays([pa.array(u[i + a]), pa.array(v[j]), pa.array(found)], ["u", "v", "cos"])

    return pairs.mapInArrow(work, "u bigint, v bigint, cos double")


def nearest_vectors(spark: SparkSession, sf_dir: str, k: int = 5) -> DataFrame:
    """Each vector's ``k`` nearest by cosine, against all vectors in blocks; of equal ones the least ids.

    Equal vectors are compared once.  Every block of different vectors meets every
    other, so this is for tables of vectors whose square is affordable; it is the
    exact reference for an index.  Cosines with a zero vector are undefined and
    stand before all others, those with null vectors after them.
    """
    from dgprop.functions.vectors import vec_norm
    from dgprop.plans.lineage import cut

    v = table(spark, sf_dir, "embeddings").filter("vec_id IS NOT NULL").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    same = v.groupBy("e").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))
    vectors = cut(same.select(F.monotonically_increasing_id().alias("u"), "e", F.coalesce(vec_norm(F.col("e")), F.lit(0.0)).alias("n"), "ids", F.col("ids")[0].alias("least")))
    n = vectors.count()
    parts = lambda each: max(1, min(1000, -(-n // each)))
    sides = [_packed(vectors.repartition(parts(each), "u"), each).toDF(*[side + c for c in ("u", "e", "n", "least", "width")]) for side, each in (("p", max(1, min(LOOKING, n // 32))), ("q", SEEN))]
    met = cut(_nearest_in_blocks(cut(sides[0]).crossJoin(cut(sides[1])), k))
    # The first of a vector's ids, one more than are asked for, as a vector's own does not count.
    few = F.slice(F.array_distinct("ids"), 1, k + 1)
    ids = vectors.select(F.col("u").alias("v"), F.explode(F.filter("ids", lambda x: F.array_contains(few, x))).alias("j"))
    best = met.join(ids, "v").groupBy("u").agg(F.array_sort(F.collect_list(F.struct((-F.round("cos", 9)).alias("c"), "j"))).alias("t"))
    own = vectors.select("u", F.explode("ids").alias("i")).join(best, "u")
    top = own.select("i", F.slice(F.filter("t", lambda x: x["j"] != F.col("i")), 1, k).alias("t"))
    top = top.groupBy("i").agg(F.slice(F.array_sort(F.flatten(F.collect_list("t"))), 1, k).alias("t"))
    return top.select((F.col("i") + VECTOR).alias("src"), F.explode("t.j").alias("j")).select("src", (F.col("j") + VECTOR).alias("dst"), F.lit(1.0).alias("w"))


def random_features(nodes: DataFrame, dim: int, seed: int = 0) -> DataFrame:
    """node and an array of ``dim`` uniform draws from a hash of seed, node and place."""
    return nodes.select("node", F.array(*[uniform(seed, F.col("node"), i) for i in range(dim)]).alias("x"))


def returned_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether an interaction of customer and part is returned: node, ts_us, label."""
    return trades(spark, sf_dir).select(F.col("src").alias("node"), "ts_us", (F.col("l_returnflag") == "R").cast("int").alias("label"))


def error_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether a user's event is an error: node, ts_us, label."""
    return interactions(spark, sf_dir).select(F.col("src").alias("node"), "ts_us", (F.col("event_type") == "error").cast("int").alias("label"))
