"""Python functions, for what built-in ones can't express or for checking those."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def squash(x: pd.Series) -> pd.Series:
    """The logistic function."""
    return 1 / (1 + np.exp(-x))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vec_sum_agg(x: pd.Series) -> list:
    """Element-wise sum of a group; ``vectors.vec_sum`` is the faster way for a known length."""
    return np.sum(np.stack(x.to_numpy()), axis=0).tolist()


class HalfEdges:
    """The signed half-edges of an event."""

    def eval(self, kind: str, src: int, dst: int, w: float) -> Iterator[tuple[int, int, float]]:
        sign = {"add_edge": 1.0, "del_edge": -1.0}.get(kind)
        if sign is not None:
            yield src, dst, sign * w
            if src != dst:
                yield dst, src, sign * w


half_edges = F.udtf(HalfEdges, returnType=T.StructType().add("a", T.LongType()).add("b", T.LongType()).add("dw", T.DoubleType()))
