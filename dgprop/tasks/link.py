"""Will two nodes be linked in the next step?  Scores from sequences of changes."""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dgprop.models.networks import LinkModel, fit_dealt, fit_partitions
from dgprop.operators.sequences import deltas, sequences, with_asked, with_earlier
from dgprop.plans.lineage import stored
from dgprop.tasks.fitting import dealt

KEPT = ("query_id", "step", "src", "dst", "label", "part")
SCORED = "query_id bigint, step int, src bigint, dst bigint, label int, part string, score double"


def padded(changes: DataFrame, length: int, dim: int, only: str | None = None) -> DataFrame:
    """step, node, x (``length`` changes, zeros first) and m (1 where there is one); ``only`` names a column that says which rows."""
    s = sequences(changes, length) if only is None else sequences(changes, length, only).filter(only)
    gap = F.lit(length) - F.size("deltas")
    zero = F.array_repeat(F.lit(0.0), dim)
    x = F.concat(F.array_repeat(zero, gap), F.col("deltas"))
    return s.select("step", "node", x.alias("x"), F.concat(F.array_repeat(F.lit(0), gap), F.array_repeat(F.lit(1), F.size("deltas"))).alias("m"))


def _joined(s: DataFrame, pairs: DataFrame, columns: tuple[str, ...]) -> DataFrame:
    """Pairs of step t with what both ends have at t - 1: nothing of the step itself is seen."""
    side = lambda end, k: s.select((F.col("step") + 1).alias("step"), F.col("node").alias(end), *[F.col(c).alias(f"{c}{k}") for c in columns])
    return pairs.join(side("src", "a"), ["step", "src"]).join(side("dst", "b"), ["step", "dst"])


def _size(packed: DataFrame) -> float:
    """The size of a change in the training rows of all parts."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for deal, n, blob in zip(*(batch.column(c) for c in ("deal", "n", "arrays")), strict=True):
                arrays = pickle.loads(blob.as_buffer())
                square = np.mean([np.mean(np.square(arrays[c]).reshape(n.as_py(), -1), axis=1) for c in ("xa", "xb")])
                yield pa.RecordBatch.from_pydict({"deal": pa.array([deal.as_py()], pa.int32()), "n": [n.as_py()], "square": [square]})

    got = sorted(packed.mapInArrow(work, "deal int, n bigint, square double").collect())
    return float(np.sqrt(sum(r["square"] * (r["n"] / sum(o["n"] for o in got)) for r in got)))


def _rows(s: DataFrame, train: DataFrame) -> DataFrame:
    """Training pairs with the sequences of both ends."""
    return _joined(s, train, ("x", "m")).select("query_id", "dst", "label", "xa", "ma", "xb", "mb")


@dataclass
class LinkTask:
    """Sequences of changes and pairs, for any number of models."""

    #: step, node, x (flat), m: of the asked ends.
    sequences: DataFrame
    #: The training pairs that models are fitted on, and those to score.
    train: DataFrame
    rest: DataFrame
    #: The training pairs with their sequences in parts, and the size of a change in them; None without pairs, or where gradients of partitions are used.
    parts: DataFrame | None = None
    size: float = 0.0
    spread: bool = False

    def fit(self, model: LinkModel, epochs: int, rate: float, seed: int) -> tuple[LinkModel, dict] | None:
        """The scaled model and its parameters; None without rows."""
        if self.spread:
            rows = _rows(self.sequences, self.train)
            size = rows.select(F.explode(F.concat("xa", "xb")).alias("v")).agg(F.sqrt(F.avg(F.col("v") * F.col("v")))).head()[0]
            if size is None:
                return None
            scaled = replace(model, scale=1 / size if size else 1.0)
            return scaled, fit_partitions(scaled, rows, epochs, rate, seed)
        if self.parts is None:
            return None
        scaled = replace(model, scale=1 / self.size if self.size else 1.0)
        return scaled, fit_dealt(scaled, self.parts, epochs, 256, rate, seed)

    def run(self, model: LinkModel, epochs: int, rate: float = 0.01, seed: int = 0) -> DataFrame:
        """Scores of the pairs; without training rows all are even."""
        got = self.fit(model, epochs, rate, seed)
        if got is None:
            return _joined(self.sequences, self.rest, ()).select("query_id", "step", "src", "dst", "label", "part", F.lit(0.5).alias("score"))
        scaled, params = got

        def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    x, m = (batch.column(c).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1) for c in ("x", "m"))
                    h = scaled.encode(params, x.reshape(*m.shape, -1), m)
                    lists = pa.ListArray.from_arrays(np.arange(0, h.size + 1, h.shape[1], dtype=np.int32), h.ravel())
                    yield pa.RecordBatch.from_arrays([batch.column("step"), batch.column("node"), lists], ["step", "node", "h"])

        def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    a, b = (batch.column(c).flatten().to_numpy().reshape(batch.num_rows, -1) for c in ("ha", "hb"))
                    found = pa.array(scaled.head(params, a, b))
                    yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in KEPT), found], [*KEPT, "score"])

        h = stored(self.sequences.mapInArrow(encode, "step int, node bigint, h array<double>"))
        return _joined(h, self.rest, ("h",)).select(*KEPT, "ha", "hb").mapInArrow(score, SCORED)


def prepare(representations: DataFrame, pairs: DataFrame, length: int, dim: int, kind: str = "diff", spread: bool = False, more: DataFrame | None = None) -> LinkTask:
    """Sequences are only made of the ends that pairs ask for, and of ``more`` (step, node); all training pairs are fitted on."""
    pairs = stored(_joined(with_earlier(representations), pairs, ()).select(*KEPT))
    train, rest = pairs.filter("part = 'train'"), pairs.filter("part <> 'train'")
    ends = reduce(DataFrame.union, [pairs.select((F.col("step") - 1).alias("step"), F.col(end).alias("node")) for end in ("src", "dst")] + ([] if more is None else [more.select("step", "node")])).distinct()
    changes = deltas(with_asked(representations, ends), kind, "asked")
    s = stored(padded(changes, length, dim, "asked").select("step", "node", F.flatten("x").alias("x"), "m"))
    n = 0 if spread else train.count()
    if not n:
        return LinkTask(s, train, rest, spread=spread)
    parts = dealt(_rows(s, train), ["query_id", "dst", "label"], LinkModel("lstm", dim, 1).arrays, n)
    return LinkTask(s, train, rest, parts, _size(parts))


def run(representations: DataFrame, pairs: DataFrame, length: int, model: LinkModel, epochs: int = 5, rate: float = 0.01, seed: int = 0, kind: str = "diff", spread: bool = False) -> DataFrame:
    """Fit on all pairs of part = train, score those of valid and test.

    The sequence of a node is encoded once for each step, and pairs are scored from
    the two states, so the number of candidates for a pair costs little.  Without
    training rows all scores are even.
    """
    return prepare(representations, pairs, length, model.d, kind, spread).run(model, epochs, rate, seed)
