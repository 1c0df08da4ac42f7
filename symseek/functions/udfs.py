"""Python functions for SQL: a scalar profile, an aggregate, and a lateral table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from symseek.functions import kernels
from symseek.operators.fold import Rules, SerialSifter


def hits_of(text: str, pattern: str, k: int) -> Iterator[tuple[int, int, int]]:
    """(start, len, dist) of every hit of one text, in order of start and length."""
    if not text:
        return
    codes, starts, sizes = kernels.joined([text], len(pattern) + k)
    at = np.arange(sizes[0])
    lengths, dist = kernels.band_distances(codes, starts[0] + at, kernels.encode(pattern), k)
    s, l = np.nonzero(dist.T <= k)
    for start, length, d in zip(s.tolist(), np.array(lengths)[l].tolist(), dist[l, s].tolist(), strict=True):
        if start + length <= sizes[0]:
            yield start, length, d


def _edit_profile(text: pd.Series, pattern: pd.Series, k: pd.Series) -> pd.Series:
    """The number of hits of a text at each distance 0 .. K."""

    def profile(t: str, p: str, top: int) -> list[int]:
        out = [0] * (top + 1)
        for _, _, d in hits_of(t or "", p, top):
            out[d] += 1
        return out

    return pd.Series([profile(t, p, int(top)) for t, p, top in zip(text, pattern, k, strict=True)])


def _kept_count(start: pd.Series, length: pd.Series, dist: pd.Series) -> int:
    """How many of a group's hits are kept."""
    order = np.lexsort((length, start))
    sifter = SerialSifter(int(dist.max()) + 1 if len(dist) else 1, Rules())
    kept = 0
    for i in order:
        kept += len(sifter.add(int(start.iloc[i]), int(length.iloc[i]), int(dist.iloc[i])))
    return kept + len(sifter.close())


class ScanPattern:
    """Occurrences of a pattern in a text: SELECT ... FROM streams, LATERAL scan_pattern(text, 'ACBDA', 2)."""

    def eval(self, text: str, pattern: str, k: int):
        sifter = SerialSifter(k + 1, Rules())
        for hit in hits_of(text or "", pattern, k):
            yield from sifter.add(*hit)
        yield from sifter.close()


def edit_profile(text: Column, pattern: Column, k: Column) -> Column:
    return F.pandas_udf(_edit_profile, "array<int>")(text, pattern, k)


def kept_count(start: Column, length: Column, dist: Column) -> Column:
    return F.pandas_udf(_kept_count, "long")(start, length, dist)


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    spark.udf.register("edit_profile", F.pandas_udf(_edit_profile, "array<int>"))
    spark.udf.register("kept_count", F.pandas_udf(_kept_count, "long"))
    spark.udtf.register("scan_pattern", F.udtf(ScanPattern, returnType="start: bigint, len: int, dist: int, decided_at: bigint"))
