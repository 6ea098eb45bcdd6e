"""Token counts of every prefix of a text by dynamic programming.

For byte-pair merging, the encoding of a prefix ends in the one token that is
compatible with the token before it, so ``count[i] = count[i - len(t)] + 1`` for
that token ``t``.  Pieces between which the tokenizer never merges are worked out
once each; a text's prefix counts are theirs, summed up.  The result is kept as
the change of the count at every code point, from which counts, truncations and
budget splits follow without another encoding.

Texts with special strings or with characters whose class may be disputed are
split by the library itself, in linear time; only where the pieces' counts then
miss the library's total, which no known text does, is every prefix encoded.  Null
and empty texts have no prefix and zero tokens; repeated rows, and rows without
doc_id, are answered each; a very long text is worked on by itself, in time that
grows with its length; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator
from functools import cache
from operator import sub

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.llm.common import documents, text_rows
from dgprop.llm.tokens import REMEMBERED, PieceTable, byte_form

_COMPOSITE = re.compile(r"\s*\S+|\s+")
_SPACE = regex.compile(r"\s+")


class PrefixCounter(PieceTable):
    """Tokens are numbered in the order in which merging makes them, single bytes first."""

    def __init__(self, path: str, remembered: int = 2 * REMEMBERED) -> None:
        super().__init__(path, remembered)
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in self.spec["model"]["merges"]]
        made = {a + b for a, b in merges}
        self.order = {t: i for i, t in enumerate(t for t in self.spec["model"]["vocab"] if t not in made)}
        self.halves: list[tuple[int, int] | None] = [None] * len(self.order)
        self.joined: dict[tuple[int, int], int] = {}
        for a, b in merges:
            self.joined[self.order[a], self.order[b]] = self.order[a + b] = len(self.halves)
            self.halves.append((self.order[a], self.order[b]))
        self.longest = max(map(len, self.order))
        self.pairs: dict[int, bool] = {}

    def follows(self, left: int, right: int) -> bool:
        """Whether two tokens can stand side by side: no merge across the border comes before theirs.

        The border's neighbours are undone from the latest merge back; at each
        step the pair at the border must not have been merged earlier.
        """
        before = len(self.halves) + 1
        while True:
            if self.joined.get((left, right), before) < before:
                return False
            for side in (0, 1) if left > right else (1, 0):
                now = (left, right)[side]
                before = now + side
                if (parts := self.halves[now]) is not None:
                    if side:
                        right = parts[0]
                    else:
                        left = parts[1]
                    break
            else:
                return True

    def value_of(self, piece: str) -> list[int]:
        """Token counts of the prefixes of one piece, by code point, from the empty one on."""
        s = byte_form(piece)
        n, token_of, known, longest = len(s), self.order.get, self.pairs, self.longest
        last, count = [0] * (n + 1), [0] * (n + 1)
        for i in range(1, n + 1):
            for j in range(i - longest if i > longest else 0, i):
                token = token_of(s[j:i])
                if token is None:
                    continue
                if j:
                    key = last[j] << 32 | token
                    fits = known.get(key)
                    if fits is None:
                        if len(known) > REMEMBERED:
                            known.clear()
                        fits = known[key] = self.follows(last[j], token)
                    if not fits:
                        continue
                last[i], count[i] = token, count[j] + 1
                break
            else:
                raise ValueError(f"no token ends the prefix {s[:i]!r}")
        if piece.isascii():
            return count
        ends = np.cumsum([len(c.encode()) for c in piece])
        return [0, *(count[e] for e in ends)]

    def value_of_run(self, run: str) -> bytes:
        if run[1:].isalpha() and (run[0] == " " or run[0].isalpha()):
            counts = self.value_of(run)  # one piece; the run is what is remembered
            return array("h", map(sub, counts[1:], counts)).tobytes()
        if run[-1] in ".," and run[1:-1].isalpha() and (run[0] == " " or run[0].isalpha()):
            counts = self.values[run[:-1]]
            return array("h", map(sub, counts[1:], counts)).tobytes() + b"\1\0"
        lead = len(run) - len(run.lstrip())
        out, base, at = [0] * (len(run) + 1), 0, 0
        for piece in self.pattern.findall(run):
            counts = self.values[piece]
            if len(piece) == 3 and piece[0] == "'" and piece[1].isalpha():
                one = self.values["'"][-1]  # cut off after one letter, it is no contraction yet
                counts = [0, one, one + self.values[piece[1]][-1], counts[-1]]
            for j in range(1, len(piece) + 1):
                out[at + j] = base + counts[j]
            at += len(piece)
            base += counts[-1]
        if lead > 1:
            out[1 : lead + 1] = self.values[run[:lead]][1:]  # cut off here, the white space is one piece
        return array("h", map(sub, out[1:], out)).tobytes()

    def split(self, text: str) -> list[str] | None:
        if super().split(text) is None:
            return None
        return _COMPOSITE.findall(text)

    def library_count(self, text: str) -> int:
        return len(self.tokenizer.encode(text, add_special_tokens=False).ids)

    def whole(self, text: str) -> bytes:
        """For texts that can't be split here: special strings are cut out, the rest is split by the library.

        Up to its last character a special string counts as ordinary text.
        """
        out, at = [], 0
        for m in self.special.finditer(text) if self.special else ():
            before = self.ordinary(text[at : m.end() - 1])
            counts = np.cumsum(np.frombuffer(before, "<i2"), dtype=np.int64)
            head = int(counts[m.start() - at - 1]) if m.start() > at else 0
            now = int(counts[-1]) if len(counts) else 0
            out += [before, (head + 1 - now).to_bytes(2, "little", signed=True)]
            at = m.end()
        out.append(self.ordinary(text[at:]))
        return b"".join(out)

    def ordinary(self, text: str) -> bytes:
        """For texts without a whole special string; the library's pieces, and where their sum is wrong, the library at every prefix."""
        if not text:
            return b""
        if self.pattern is not None and self.normalizer is None:
            runs = None if self.special and self.special.search(text) else super().split(text)
            if runs is not None:
                return b"".join(map(self.runs.__getitem__, _COMPOSITE.findall(text)))
            pieces = [text[a:b] for _, (a, b) in self.tokenizer.pre_tokenizer.pre_tokenize_str(text)]
            if "".join(pieces) == text:
                counts = self.over(pieces)
                if counts[-1] == self.library_count(text):
                    return np.diff(counts).astype("<i2").tobytes()
        return np.diff([0, *(self.library_count(text[:i]) for i in range(1, len(text) + 1))]).astype("<i2").tobytes()

    def over(self, pieces: list[str]) -> list[int]:
        """Token counts of the prefixes of consecutive pieces; cut off in white space, all of that is one piece."""
        out, i = [0], 0
        while i < len(pieces):
            base, space = out[-1], ""
            total = base
            while i < len(pieces) and _SPACE.fullmatch(pieces[i]):
                space += pieces[i]
                total += self.values[pieces[i]][-1]
                i += 1
            piece = pieces[i] if i < len(pieces) else ""
            lead = 1 if space and piece[:1] == " " else 0
            if space:
                out += [base + c for c in self.values[space + piece[:lead]][1:]]
                if not piece:
                    out[-1] = total
            if piece:
                counts = self.values[piece]
                if len(piece) == 3 and piece[0] == "'" and piece[1].isalpha():
                    one = self.values["'"][-1]
                    counts = [0, one, one + self.values[piece[1]][-1], counts[-1]]
                out += [total + c for c in counts[1 + lead :]]
                i += 1
        return out

    def deltas(self, text: str) -> bytes:
        runs = self.split(text)
        return self.whole(text) if runs is None else b"".join(map(self.runs.__getitem__, runs))


@cache
def counter(path: str) -> PrefixCounter:
    return PrefixCounter(path)


def prefix_counts(docs: DataFrame, vocabulary: str) -> DataFrame:
    """doc_id, n_bytes, n_tokens and prefix_deltas: 16-bit changes of the token count, one per code point."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = counter(vocabulary)
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                texts = part.column("text")
                deltas = [table.deltas(t) for t in texts.to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column("doc_id"),
                        pc.binary_length(texts).cast(pa.int64()),
                        pa.array([int(np.frombuffer(d, "<i2").sum()) for d in deltas], pa.int64()),
                        pa.array(deltas, pa.binary()),
                    ],
                    ["doc_id", "n_bytes", "n_tokens", "prefix_deltas"],
                )

    return text_rows(docs).mapInArrow(work, "doc_id bigint, n_bytes bigint, n_tokens bigint, prefix_deltas binary")


def counts_of(deltas: bytes) -> np.ndarray:
    """Token counts of all prefixes, from the empty one to the whole text."""
    return np.concatenate(([0], np.cumsum(np.frombuffer(deltas, "<i2"), dtype=np.int64)))


def tokens_at(deltas: Column, n_chars: Column) -> Column:
    """Tokens of the prefix of ``n_chars`` code points."""

    @F.pandas_udf("bigint")
    def at(d: pd.Series, n: pd.Series) -> pd.Series:
        return pd.Series([int(counts_of(x)[min(max(int(k), 0), len(x) // 2)]) for x, k in zip(d, n, strict=True)])

    return at(deltas, n_chars)


def chars_within(deltas: Column, budget: int) -> Column:
    """Code points of the longest prefix with at most ``budget`` tokens."""

    @F.pandas_udf("bigint")
    def within(d: pd.Series) -> pd.Series:
        return pd.Series([int(np.flatnonzero(counts_of(x) <= budget)[-1]) if budget >= 0 else 0 for x in d])

    return within(deltas)


def op10_prefix_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    counts = prefix_counts(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))
    return counts.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > 1024).alias("over_limit"))
