"""The training-data operators against brute force, on small rows with the hard cases."""

import collections
import hashlib
import math
import re
import zlib

import numpy as np
import pytest

pytest.importorskip("dgprop.llm")

import public_tokenizers  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from dgprop.llm import contexttree, fingerprints, mixing, packing, personaldata, prefixcounts, qualityrules, shinglejoin, tokenfiles, toxicity  # noqa: E402
from dgprop.llm.common import new_folder  # noqa: E402
from dgprop.llm.components import components  # noqa: E402
from dgprop.llm.tokens import Encoder  # noqa: E402

WORD = r"[^\x20\x09-\x0D]+"
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
BYTE_VOCAB, WORD_VOCAB = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
LONG = " ".join(f"w{i * 7919 % 1000}" for i in range(3000))
HARD = [
    None, "", "   ", "one", "two words", "A b C d E", "a b c d e", "A\tb\nc d  e", LONG, LONG, LONG + " extra", LONG.replace("w7 ", "x7 "), "x" * 3000,
    "mail me at a.b@c.de or b@c_x@d.e, 10.0.0.1 and 300.1.1.1, 4111 1111 1111 1111, +1 (705) 555-2820", "l'été c’est ́x 日本語 🙂🙂", "same line here\nsame line here\nother", "a b c a b c a b c",
    "<|endoftext|> hi <|startoftext|>", "we're don't 'x !'re  \n\n  end", "# * $ % & | < >",
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en" if i % 3 else None, f"src{i % 4}", i, "extra") for i, t in enumerate(HARD)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint, n_words string").repartition(3)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.limit(0)


def words(t):
    return re.findall(WORD, t or "")


def shingles(t):
    w = words((t or "").translate(LOW))
    return frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def brute_components(texts):
    sets = {i: shingles(t) for i, t in texts.items()}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in sets:
        for j in sets:
            if i < j and sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), find(i)) for i in sets}


def test_join_equals_brute_force(spark, docs):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in shinglejoin.linked_components(docs).collect()}
    assert got == brute_components(dict(enumerate(HARD)))


def test_join_finds_chains_and_edits(spark):
    """Copies that are similar to their neighbours only, one word after the other."""
    base = [f"t{i}" for i in range(120)]
    texts = {}
    for i in range(40):
        w = list(base)
        for k in range(i):
            w[(k * 13) % 120] = f"e{k}"
        texts[i] = " ".join(w)
    texts |= {100 + i: " ".join(base[:60] + [f"z{i}_{k}" for k in range(60)]) for i in range(20)}
    df = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in shinglejoin.linked_components(df).collect()}
    assert got == brute_components(texts)
    kept = shinglejoin.one_of_each(df)
    assert {r["doc_id"] for r in kept.collect()} == {c for _, c in got.values()}


def test_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(1, 50)] + [(100, 200), (300, 200), (7, 7)], "a bigint, b bigint")
    got = {r["node"]: r["root"] for r in components(edges).collect()}
    assert got == {i: 1 for i in range(1, 51)} | {100: 100, 200: 100, 300: 100}


def test_empty_tables(spark, empty):
    assert shinglejoin.linked_components(empty).count() == 0
    assert qualityrules.judge(empty).count() == qualityrules.keep_good(empty).count() == 0
    assert personaldata.find_spans(empty).count() == personaldata.redact(empty).count() == 0
    assert packing.pack_documents(empty, WORD_VOCAB).count() == 0
    assert prefixcounts.prefix_counts(empty, BYTE_VOCAB).count() == 0
    assert mixing.mix(empty, F.lit("d"), {}, 0.5).count() == 0
    assert contexttree.score_texts(empty, F.lit(True)).count() == 0
    assert fingerprints.with_next(empty.select("doc_id", "text")).count() == 0
    folder = new_folder(spark, "none")
    tokenfiles.write_token_files(empty, folder, BYTE_VOCAB, 0)
    assert tokenfiles.read_token_files(spark, folder, 2).count() == 0


def test_quality_counts(docs):
    got = {r["doc_id"]: r for r in qualityrules.judge(docs).collect()}
    for i, t in enumerate(HARD):
        w, r = words(t), got[i]
        c = collections.Counter(zip(w, w[1:], w[2:]))
        covered = {k + j for k in range(len(w) - 2) if c[tuple(w[k : k + 3])] > 1 for j in range(3)}
        lines = [x for x in (t or "").split("\n") if re.search(WORD, x)]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(covered))
        assert r["base_failed"] == (len(w) < 50 or 100 * len(covered) > 50 * len(w))
        assert not (r["base_failed"] and r["kept"])
    assert qualityrules.keep_good(docs).columns == docs.columns


def test_expectation_maximisation_finds_planted_accuracies():
    """Votes of five rules on documents of which 70 % are good; the fourth rule is of no use."""
    rng = np.random.default_rng(0)
    good = rng.random(20_000) < 0.7
    right = [0.9, 0.8, 0.85, 0.5, 0.75]
    votes = np.stack([np.where(rng.random(20_000) < 0.2, 0, np.where((rng.random(20_000) < p) == good, 1, -1)) for p in right], 1)
    patterns = collections.Counter(map(tuple, votes.tolist()))
    model = qualityrules.fit(list(patterns.items()))
    assert model.good_share == pytest.approx(0.7, abs=0.03)
    for j, p in enumerate(right):
        assert model.good_votes[j][2] / (model.good_votes[j][0] + model.good_votes[j][2]) == pytest.approx(p, abs=0.03)


def test_a_bad_vote_lowers_the_posterior_and_a_rarer_fault_is_found():
    """Two faults that never meet: repetition, which two rules see, and symbols, which one sees."""
    patterns = [((1, 1, 1), 8_000), ((-1, -1, 1), 600), ((-1, 0, 1), 100), ((0, -1, 1), 100), ((1, 1, -1), 350), ((0, 1, 1), 60), ((1, 0, -1), 100)]
    model = qualityrules.fit(patterns)
    for v in np.ndindex(3, 3, 3):
        votes = [x - 1 for x in v]
        for j in range(3):
            chances = [model.chance((*votes[:j], x, *votes[j + 1 :])) for x in (-1, 0, 1)]
            assert chances[0] < chances[1] <= chances[2]
    assert model.chance((1, 1, 1)) > 0.5 > max(model.chance((-1, -1, 1)), model.chance((1, 0, -1)))


def luhn(d):
    return sum(int(c) if i % 2 == 0 else (2 * int(c) - 9 if c > "4" else 2 * int(c)) for i, c in enumerate(reversed(d))) % 10 == 0


PLAIN = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]


def plain_spans(t):
    out = []
    for j, (k, p) in enumerate(PLAIN):
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m.group())
            if k == "email" or (k == "ip" and all(int(x) <= 255 for x in m.group().split("."))) or (k == "card" and 14 <= len(d) <= 19 and luhn(d)) or (k == "phone" and 10 <= len(d) <= 15):
                out.append((m.start(), j, f"{k}:{m.start()}:{m.end()}"))
    return ",".join(x[2] for x in sorted(out))


def test_personal_data_base_spans(spark):
    texts = [*HARD, "a@b.c_x@d.e y 1.2.3.4.5.6.7.8", "1" * 30000, "a" * 30000 + "@b.co", "a." * 5000 + "@x.y x@" + "a." * 5000 + "b", "1 " * 4000, "🙂 q@r.st 🙂 +49 30 1234567 8", "0001.002.3.255"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for r in personaldata.find_spans(df).collect():
        want = plain_spans(texts[r["doc_id"]] or "")
        assert r["base_spans"] == want
        assert r["base_sha256"] == hashlib.sha256(want.encode()).hexdigest()
        assert set(filter(None, want.split(","))) <= set(r["spans"].split(","))
    clean = {r["doc_id"]: r["text"] for r in personaldata.redact(df).collect()}
    assert clean[13].startswith("mail me at <EMAIL> or ") and clean[13].endswith(", <IP> and 300.1.1.1, <CARD>, <PHONE>")
    assert clean[0] is None and clean[8] == LONG


def test_boosted_trees_add_what_looks_like_base_spans():
    x = (3, 3, 2, 2, 1, 0, 0, 1, 0)
    off = (3, 3, 2, 2, 0, 2, 2, 0, 3)
    model = personaldata.boost([(x, 1, f, 50) for f in (0, 1)] + [(off, 0, f, 50) for f in (0, 1)])
    assert model.score(x) >= model.thresholds[3] > model.score(off)
    assert personaldata.boost([]).thresholds == [math.inf] * 4


@pytest.mark.parametrize("path", [BYTE_VOCAB, WORD_VOCAB])
def test_cached_ids_equal_the_library(path):
    e = Encoder(path, remembered=16)
    texts = [*[t or "" for t in HARD], "a  b\n\n c\t d ", "a\r\n b \x1c c\xa0d\x85e", "ǅ İstanbul ΣΑΣ", "1234 5,6.7 (8)"]
    assert e.encode(texts) == [e.whole(t) for t in texts]


def test_prefix_counts_equal_encoding_every_prefix():
    table = prefixcounts.PrefixCounter(BYTE_VOCAB)
    for t in [*[(t or "")[:160] for t in HARD], "a  b\n\n c\t d ", "=" * 40, "a" * 40, "é" * 9, " 'll 'l '"]:
        counts = prefixcounts.counts_of(table.deltas(t))
        assert counts.tolist() == [table.library_count(t[:i]) for i in range(len(t) + 1)]


def test_prefix_questions(spark, docs):
    counts = prefixcounts.prefix_counts(docs, BYTE_VOCAB)
    rows = counts.select("doc_id", "n_tokens", prefixcounts.chars_within(F.col("prefix_deltas"), 5).alias("fits"), prefixcounts.tokens_at(F.col("prefix_deltas"), F.lit(3)).alias("at3")).collect()
    table = prefixcounts.PrefixCounter(BYTE_VOCAB)
    for r in rows:
        t = HARD[r["doc_id"]] or ""
        assert r["n_tokens"] == table.library_count(t)
        assert r["at3"] == table.library_count(t[:3])
        assert table.library_count(t[: r["fits"]]) <= 5


def test_token_files_round_trip(spark, docs):
    for width in (2, 4):
        folder = new_folder(spark, "round-trip")
        tokenfiles.write_token_files(docs.union(docs.filter("doc_id = 5")), folder, BYTE_VOCAB, 0, 3, width)
        rows = sorted(tokenfiles.read_token_files(spark, folder, width).collect(), key=lambda r: r["start"])
        e, at = Encoder(BYTE_VOCAB), 0
        assert [r["doc_id"] for r in rows] == sorted([*range(len(HARD)), 5])
        for r in rows:
            ids = e.whole(HARD[r["doc_id"]] or "") + bytes(4)
            assert (r["start"], r["n_tokens"], bytes(r["ids"])) == (at, len(ids) // 4, ids)
            at += len(ids) // 4


def test_bin_completion():
    rng = np.random.default_rng(1)
    assert packing.bin_completion([6, 6, 6, 4, 4, 4], 10) and len(packing.bin_completion([6, 6, 6, 4, 4, 4], 10)) == 3
    # Best fit decreasing needs more bins here than there have to be.
    hard = [50, 50, 34, 34, 33, 33, 33, 33] + [60, 25, 15, 40, 35, 25]
    assert len(packing.bin_completion(hard, 100)) <= len(packing.best_fit_decreasing(hard, 100))
    for _ in range(30):
        lengths = rng.integers(1, 60, 24).tolist()
        bins = packing.bin_completion(lengths, 100, max_nodes=2000)
        assert sorted(i for b in bins for i in b) == list(range(24))
        assert all(sum(lengths[i] for i in b) <= 100 for b in bins)
        assert -(-sum(lengths) // 100) <= len(bins) <= len(packing.best_fit_decreasing(lengths, 100))
    planted = [p for _ in range(8) for p in (47, 31, 22)]
    assert len(packing.bin_completion(planted, 100)) == 8
    assert packing.bin_completion([], 100) == []


def test_packing_places(docs):
    rows = packing.pack_documents(docs, WORD_VOCAB, capacity=64).toPandas()
    e = Encoder(WORD_VOCAB)
    for (doc,), p in rows.groupby(["doc_id"]):
        ids = e.whole(HARD[doc] or "") + (1).to_bytes(4, "little")
        p = p.sort_values("piece")
        assert p["start"].tolist() == list(range(0, len(ids) // 4, 64)) and p["length"].sum() == len(ids) // 4
        assert p["ids_crc32"].tolist() == [zlib.crc32(ids[4 * a : 4 * (a + n)]) for a, n in zip(p["start"], p["length"], strict=True)]
    for _, s in rows.groupby("sequence_id"):
        s = s.sort_values("offset")
        assert s["offset"].tolist() == [0, *s["length"].cumsum()[:-1]] and s["length"].sum() <= 64


def test_budgets():
    tokens = {("a", "x", "1"): 10, ("a", "x", "2"): 100, ("a", "y", "1"): 100, ("b", "x", "1"): 100}
    got = mixing.budgets(tokens, {("a",): 3, ("b",): 1}, 160)
    assert got == {("a", "x", "1"): 10, ("a", "x", "2"): 50, ("a", "y", "1"): 60, ("b", "x", "1"): 40}
    assert mixing.budgets(tokens, {}, 10**6) == tokens
    # The shortage of a leaf goes to its sibling; only what the branch can't take goes up.
    got = mixing.budgets({("a", "x", "1"): 5, ("a", "x", "2"): 5, ("b", "x", "1"): 100}, {}, 60)
    assert got == {("a", "x", "1"): 5, ("a", "x", "2"): 5, ("b", "x", "1"): 50}
    assert mixing.budgets({("a", "x", "1"): 5}, {}, 100, max_epochs=3) == {("a", "x", "1"): 15}


def test_mix_equals_brute_force(spark):
    rows = [(i, " ".join(["w"] * (i % 9)), "en", f"src{i % 3}", 0) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    got = mixing.mix_table(df, F.lit("d"), {("d", "en", "src0"): 5.0}, 0.7, max_epochs=2, seed=3).toPandas()
    tokens = collections.Counter()
    for i, t, lang, source, _ in rows:
        tokens["d", lang, source] += len(t.split())
    budget = mixing.budgets(dict(tokens), {("d", "en", "src0"): 5.0}, int(sum(tokens.values()) * 0.7), 2)
    want = collections.Counter()
    for leaf, b in budget.items():
        mine = [(i, len(t.split())) for i, t, _, s, _ in rows if s == leaf[2]]
        full, rest = divmod(b, tokens[leaf])
        for e in range(full):
            want.update((i, e) for i, _ in mine)
        at = 0
        for i, n in sorted(mine, key=lambda m: (int(hashlib.md5(f"3:{full}:{m[0]}".encode()).hexdigest()[:13], 16), m[0])):
            if at < rest:
                want[i, full] += 1
            at += n
    assert collections.Counter(zip(got["doc_id"], got["epoch"], strict=True)) == want
    assert mixing.mix(df, F.lit("d"), {}, 0.5).columns == df.columns


def test_next_document(spark):
    ids = [5, 1, 9, 100, 7, 3, 10**12]
    df = spark.createDataFrame([(i, f"t{i}") for i in ids], "doc_id bigint, text string")
    got = {r["doc_id"]: (r["next_id"], r["next_text"]) for r in fingerprints.with_next(df).collect()}
    down = sorted(ids, reverse=True)
    assert got == {i: (n, f"t{n}") for i, n in zip(down, down[1:] + down[:1], strict=True)}


def test_next_document_over_many_buckets(spark, monkeypatch):
    monkeypatch.setattr(fingerprints, "BUCKET_ROWS", 3)
    for most in (200, 4):
        monkeypatch.setattr(fingerprints, "MOST_RANGES", most)
        ids = sorted({(i * i * 31) % 4001 for i in range(90)}, reverse=True)
        df = spark.createDataFrame([(i, f"t{i}") for i in ids], "doc_id bigint, text string").repartition(3)
        got = {r["doc_id"]: r["next_id"] for r in fingerprints.with_next(df).collect()}
        assert got == dict(zip(ids, ids[1:] + ids[:1], strict=True))


def test_samples_collide_as_generalised_jaccard(spark):
    rng = np.random.default_rng(0)
    pairs = []
    for i in range(120):
        a = collections.Counter({f"w{i}_{k}": int(rng.integers(1, 6)) for k in range(30)})
        b = collections.Counter({f"w{i}_{k}": int(rng.integers(1, 6)) for k in range(10, 40)})
        pairs.append((i, a, b, sum((a & b).values()) / sum((a | b).values())))
    rows = [(2 * i + s, " ".join(c.elements())) for i, a, b, _ in pairs for s, c in enumerate((a, b))]
    made = {r["row"]: r["samples"] for r in fingerprints.signatures(spark.createDataFrame(rows, "row bigint, text string"), ["row"], 16).collect()}
    rate = np.mean([np.mean(np.array(made[2 * i]) == np.array(made[2 * i + 1])) for i, *_ in pairs])
    assert rate == pytest.approx(np.mean([p[3] for p in pairs]), abs=0.03)


def test_likeness_error_of_the_samples_taken(spark):
    """All samples that the query takes: the root mean square error stays below what 16 samples give (0.12)."""
    texts = []
    for i in range(80):
        shared = 8 if i % 2 else 6
        texts += [(3 * i + side, " ".join(f"w{i}_{k}" for k in range(first, first + 90))) for side, first in enumerate((0, 90 - 9 * shared))]
    n = fingerprints.SAMPLES
    made = {r["row"]: np.array(r["samples"]) for r in fingerprints.signatures(spark.createDataFrame(texts, "row bigint, text string"), ["row"]).collect()}
    errors = []
    for i in range(80):
        both = 90 * (8 if i % 2 else 6) // 10
        errors.append(np.mean(made[3 * i] == made[3 * i + 1]) - both / (180 - both))
    assert {len(v) for v in made.values()} == {n} and n >= 64
    assert np.sqrt(np.mean(np.square(errors))) < 0.08
    assert len({tuple(v) for v in np.stack([made[0][k : k + 16] for k in range(0, n, 16)]).tolist()}) == n // 16


def test_context_tree_probabilities_sum_to_one():
    import pyarrow as pa

    texts = pa.array(["the cat sat on the mat", "The dog ate the cat", None, ""])
    (_, _), (keys, counts) = contexttree.block_keys(texts, np.array([True, True, True, True]))
    trees = contexttree.Subtrees(keys, counts)
    top = contexttree.TopNodes(*trees.summary())
    for context in np.unique(keys >> np.uint64(8))[:5].tolist() + [0x7A7A7A7A]:
        every = (np.uint64(context) << np.uint64(8)) | np.arange(256, dtype=np.uint64)
        k, c = contexttree.summed(np.concatenate((keys, every)), np.concatenate((counts, np.zeros(256, np.int64))))
        chance = np.exp(contexttree.Subtrees(k, c).log_chances(top)[np.searchsorted(k, every)])
        assert chance.sum() == pytest.approx(1)


def test_context_tree_against_a_plain_tree():
    """The same mixture by recursion over dictionaries, one byte deep enough to follow by hand."""
    import pyarrow as pa

    texts = ["abab", "abba ab", ""]
    (_, _), (keys, counts) = contexttree.block_keys(pa.array(texts), np.ones(3, bool))
    got = contexttree.Subtrees(keys, counts).log_chances(contexttree.TopNodes(*contexttree.Subtrees(keys, counts).summary()))
    table = dict(zip(keys.tolist(), counts.tolist(), strict=True))

    def log_kt(n0, n1):
        return math.lgamma(n0 + 0.5) + math.lgamma(n1 + 0.5) - math.lgamma(n0 + n1 + 1) - math.log(math.pi)

    def node_counts(context, node):
        n = [0, 0]
        depth, j = len(context), node.bit_length() - 1
        for key, c in table.items():
            symbol, before = key & 255, [key >> 8 * (contexttree.DEPTH - i) & 255 for i in range(contexttree.DEPTH)]
            if before[:depth] == context and (symbol >> (8 - j) | 1 << j) == node:
                n[symbol >> (7 - j) & 1] += c
        return n

    def log_mixed(context, node):
        own = log_kt(*node_counts(context, node))
        if len(context) == contexttree.DEPTH:
            return own
        below = {key >> 8 * (contexttree.DEPTH - len(context)) & 255 for key in table if [key >> 8 * (contexttree.DEPTH - i) & 255 for i in range(len(context))] == context}
        return math.log(0.5) + np.logaddexp(own, sum(log_mixed([*context, b], node) for b in below))

    def chance(context, node, bit):
        p = None
        for depth in range(contexttree.DEPTH, -1, -1):
            part = context[:depth]
            n = node_counts(part, node)
            own = (n[bit] + 0.5) / (sum(n) + 1)
            if depth == contexttree.DEPTH:
                p = own
            else:
                share = math.exp(math.log(0.5) + log_kt(*n) - log_mixed(part, node))
                p = share * own + (1 - share) * p
        return p

    for key, value in list(zip(keys.tolist(), got, strict=True))[:4]:
        symbol, context = key & 255, [key >> 8 * (contexttree.DEPTH - i) & 255 for i in range(contexttree.DEPTH)]
        want = sum(math.log(chance(context, symbol >> (8 - j) | 1 << j, symbol >> (7 - j) & 1)) for j in range(8))
        assert value == pytest.approx(want, abs=1e-9)


def test_base_score(docs):
    got = {r["doc_id"]: r for r in contexttree.score_texts(docs, F.col("doc_id") % 4 != 1).collect()}
    tokens = {i: [*words((t or "").translate(LOW)), None] for i, t in enumerate(HARD)}
    c = collections.Counter(w for i, ws in tokens.items() if i % 4 != 1 for w in ws)
    n, v = sum(c.values()), len(c)
    for i, ws in tokens.items():
        r = got[i]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(ws), sum(c[w] > 0 for w in ws), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in ws))
        assert r["score"] < 0


def test_toxicity(spark):
    rng = np.random.default_rng(0)
    plain = [f"word{k}" for k in range(40)]
    texts, labels = [], []
    for i in range(400):
        bad = i % 5 == 0
        w = rng.choice(plain, 20).tolist() + (["horrid", "nasty"] if bad else [])
        texts.append((i, " ".join(w)))
        labels.append((i, 1, int(bad)))
    texts += [(1000, None), (1001, "")]
    docs = spark.createDataFrame(texts, "doc_id bigint, text string")
    model = toxicity.fit(toxicity.training_rows(docs, spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int")))
    rows = {r["doc_id"]: r for r in toxicity.score_toxicity(docs, model).collect()}
    for i, _, y in labels:
        assert rows[i]["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0)
        assert rows[i]["predicted"] == y
    assert 0 <= rows[1000]["score"] == rows[1001]["score"] < 0.5
    none = toxicity.fit(toxicity.training_rows(docs, spark.createDataFrame([], "doc_id bigint, quality int, toxic int")))
    assert toxicity.score_toxicity(docs, none).count() == 402


def test_pipeline_stages(spark):
    corpus = pytest.importorskip("corpus_pipeline")
    from dgprop.llm.common import documents, save

    sf = "/root/testdata/sf0.001"
    docs = documents(spark, sf)
    before = docs.count()
    for i, (_, stage) in enumerate(corpus.STAGES):
        docs = save(stage(spark, docs, sf), "stage")
        if i + 1 < len(corpus.STAGES):
            assert docs.columns == corpus.COLUMNS and 0 < docs.count() <= before
            before = docs.count()
            if i == 1:
                found = [r["component_id"] for r in shinglejoin.linked_components(docs).collect()]
                assert len(found) == len(set(found))
    assert {r["doc_id"] for r in docs.select("doc_id").distinct().collect()} and docs.filter("piece = 0").count() == before
