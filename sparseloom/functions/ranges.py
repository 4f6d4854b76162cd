"""Ranges of a key, cut at its quantiles, and the range that a value falls into."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def upto_cuts(value: Column, cuts: list[int], width: int = 64) -> Column:
    """How many of the sorted cuts are at or before the value: first among every `width`-th, then among those in between."""
    if not cuts:
        return F.lit(0).cast("long")
    upto = lambda xs: F.size(F.filter(xs, lambda c: c <= value))
    longs = lambda xs: F.array(*map(F.lit, xs)).cast("array<long>")
    blocks = [cuts[i : i + width] for i in range(0, len(cuts), width)]
    whole = upto(longs([b[-1] for b in blocks]))
    return (whole * width + upto(F.coalesce(F.get(F.array(*map(longs, blocks)), whole), longs([])))).cast("long")


def range_of(df: DataFrame, key: str, parts: int) -> Column:
    """Number of the range of `key` (a long) that a row is in, of at most `parts` with about equally many rows."""
    if parts < 2:
        return F.lit(0).cast("long")
    shares = [k / parts for k in range(1, parts)]
    cuts = df.agg(F.percentile_approx(key, shares, 10 * parts)).first()[0] or []
    return upto_cuts(F.col(key), sorted(set(cuts)))
