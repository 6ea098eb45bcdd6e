"""Exact tokenisation with the tokenizers library, merging each distinct piece once.

The supported vocabularies split a text by a pattern before they merge anything,
so a text's ids are the ids of its pieces, one after the other.  The library
normalises the text and its BPE model encodes every distinct piece once per
worker; only the splitting is repeated here.  A text that holds a special
token's string, or characters on whose class the two regular-expression engines
might disagree, is encoded whole by the library.  The tests compare both ways.
"""

from __future__ import annotations

import json
import os
import re
from functools import cache

import numpy as np
import regex

#: Pieces that a worker remembers; beyond it, pieces live for one call only.
REMEMBERED = 450_000
#: A longer piece is never remembered.
LONGEST_REMEMBERED = 64

# Fixed value: the splitting pattern of byte-level BPE with use_regex.
_BYTE_LEVEL = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_RUNS = re.compile(r" ?\S+|\s+(?!\S)|\s+")
_FOREIGN = regex.compile("[^\x00-ɏ‐-‧€]")
_CONTROLS = "\x0b\x0c\x1c\x1d\x1e\x1f\x85\xa0"


def _byte_alphabet() -> list[str]:
    """The printable character that stands for each byte: itself if printable, else the next from 256 on."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = iter(range(256, 512))
    return [chr(b) if b in printable else chr(next(others)) for b in range(256)]


BYTE_ALPHABET = _byte_alphabet()
_TO_ALPHABET = dict(enumerate(BYTE_ALPHABET))


def byte_form(piece: str) -> str:
    """A piece as the byte-level model reads it."""
    if piece.isascii() and piece[1:].isalnum():
        return BYTE_ALPHABET[ord(piece[0])] + piece[1:]
    return piece.encode().decode("latin-1").translate(_TO_ALPHABET)


class _Memo(dict):
    """Values of keys, worked out when first asked for; once full, no more are kept."""

    def __init__(self, value, room: int) -> None:
        super().__init__()
        self.value, self.room = value, room

    def __missing__(self, key: str):
        found = self.value(key)
        if len(self) < self.room and len(key) <= LONGEST_REMEMBERED:
            self[key] = found
        return found


class PieceTable:
    """Splits texts into runs and those into pieces; keeps a value for each distinct one."""

    def __init__(self, path: str, remembered: int = REMEMBERED) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # Spark's tasks are the parallelism
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.spec = spec
        self.pattern = self._pattern(spec)
        self.normalizer = self.tokenizer.normalizer
        # Below the foreign characters there is nothing to compose, and white space splits anyway.
        steps = [n.get("type") for n in (spec.get("normalizer") or {}).get("normalizers", [])]
        self.lowers = steps == ["NFC", "Replace", "Lowercase"] and spec["normalizer"]["normalizers"][1]["pattern"] == {"Regex": "\\s+"}
        specials = [regex.escape(t["content"]) for t in spec.get("added_tokens", [])]
        self.special = regex.compile("|".join(specials)) if specials else None
        self.spaced = self.pattern is not None and self.pattern.pattern == _BYTE_LEVEL
        self.model = self.tokenizer.model
        self.values = _Memo(self.value_of, remembered // 4)
        self.runs = _Memo(self.value_of_run, remembered)

    @staticmethod
    def _pattern(spec: dict):
        """The compiled splitting pattern, or None if the tokenizer is of another build."""
        pre, model = spec.get("pre_tokenizer") or {}, spec["model"]
        if model["type"] != "BPE" or model.get("dropout") or model.get("unk_token"):
            return None
        if pre.get("type") == "ByteLevel" and pre.get("use_regex") and not pre.get("add_prefix_space"):
            return regex.compile(_BYTE_LEVEL)
        steps = pre.get("pretokenizers", []) if pre.get("type") == "Sequence" else []
        if len(steps) == 2 and steps[0].get("type") == "Split" and steps[0].get("behavior") == "Removed" and steps[0].get("invert") and steps[1].get("type") == "ByteLevel" and not steps[1].get("use_regex") and not steps[1].get("add_prefix_space"):
            return regex.compile(steps[0]["pattern"]["Regex"])
        return None

    def split(self, text: str) -> list[str] | None:
        """Runs of a text between which no piece reaches, or None if the library has to encode it whole.

        A run is a word with the space that leads it, or other white space.
        """
        if self.pattern is None or (self.special and "<" in text and self.special.search(text)):
            return None
        if not text.isascii() and _FOREIGN.search(text):
            return None
        for c in _CONTROLS:
            if c in text:
                return None
        if self.lowers:
            text = text.lower()
        elif self.normalizer is not None:
            text = self.normalizer.normalize_str(text)
        return _RUNS.findall(text) if self.spaced else text.split()

    def value_of(self, piece: str):
        raise NotImplementedError

    def value_of_run(self, run: str):
        raise NotImplementedError


class Encoder(PieceTable):
    """Token ids of texts as little-endian unsigned 32-bit bytes."""

    def __init__(self, path: str, remembered: int = REMEMBERED) -> None:
        super().__init__(path, remembered)
        self.id_bytes = [i.to_bytes(4, "little") for i in range(self.tokenizer.get_vocab_size(with_added_tokens=True))]

    def whole(self, text: str) -> bytes:
        return np.asarray(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def value_of(self, piece: str) -> bytes:
        as_bytes = self.id_bytes
        return b"".join([as_bytes[t.id] for t in self.model.tokenize(byte_form(piece))])

    def value_of_run(self, run: str) -> bytes:
        get = self.values.__getitem__
        if run[1:].isalpha() and (run[0] == " " or run[0].isalpha()):
            return self.value_of(run)  # one piece; the run is what is remembered
        if run[-1] in ".," and run[1:-1].isalpha() and (run[0] == " " or run[0].isalpha()):
            return get(run[:-1]) + get(run[-1])
        return b"".join([get(p) for p in self.pattern.findall(run)])

    def encode(self, texts: list[str | None]) -> list[bytes]:
        get, out = self.runs.__getitem__, []
        for t in texts:
            runs = self.split(t or "")
            out.append(self.whole(t) if runs is None else b"".join(map(get, runs)))
        return out


@cache
def encoder(path: str) -> Encoder:
    """The worker's encoder for a vocabulary file."""
    return Encoder(path)
