"""The method's functions for SQL: call register() once for a session."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from veilwalk.operators.align import align_many


@F.pandas_udf(T.DoubleType())
def align_dissimilarity(left: pd.Series, right: pd.Series) -> pd.Series:
    """Alignment cost of two arrays of rows; null where either is null or empty."""
    ok = [i for i, (a, b) in enumerate(zip(left, right, strict=True)) if a is not None and b is not None and len(a) and len(b)]
    out = np.full(len(left), np.nan)
    stack = lambda x: np.stack([np.asarray(r, np.float64) for r in x])
    if ok:
        out[ok] = align_many([stack(left.iloc[i]) for i in ok], [stack(right.iloc[i]) for i in ok])
    return pd.Series(out).astype(object).where(~np.isnan(out), None)


class WalkPairs:
    """Pairs of a walk's positions at most window apart, both directions."""

    def eval(self, seq: list[int], window: int) -> Iterator[tuple[int, int]]:
        for i, a in enumerate(seq or []):
            for j in range(max(0, i - window), min(len(seq), i + window + 1)):
                if i != j:
                    yield a, seq[j]


class NearestLeaves:
    """The m ordinals nearest to one in a rank tree of n leaves: by the size of the common subtree, then by ordinal."""

    def eval(self, ordinal: int, n: int, m: int) -> Iterator[tuple[int, int]]:
        found, span = 0, 1
        low, high = ordinal, ordinal + 1
        while found < m and (low > 0 or high < n):
            span *= 2
            a, b = ordinal // span * span, min(n, ordinal // span * span + span)
            for x in [*range(a, low), *range(high, b)]:
                if found < m:
                    yield x, b - a
                    found += 1
            low, high = a, b


def register(spark: SparkSession) -> None:
    spark.udf.register("align_dissimilarity", align_dissimilarity)
    spark.udtf.register("walk_pairs", F.udtf(WalkPairs, returnType="a bigint, b bigint"))
    spark.udtf.register("nearest_leaves", F.udtf(NearestLeaves, returnType="ordinal bigint, leaves bigint"))
