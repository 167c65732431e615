"""Numeric features: bounds and histogram buckets in exact integer arithmetic."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


def bucket(value: Column, low: Column, high: Column, buckets: int) -> Column:
    """floor((v - low) / (high - low) * buckets) on longs; 0 where high = low; null stays null."""
    v = value.cast("long")
    inside = F.least(F.greatest(v, low), high)  # pinned bounds: values outside clamp
    whole = (inside - low) * F.lit(buckets)
    width = high - low
    return F.when(v.isNull(), None).when(width == 0, F.lit(0)).otherwise((whole - F.pmod(whole, width)) / width).cast("long")


def bounds(entries: DataFrame, features: list[str]) -> DataFrame:
    """One row with ``lo_f`` and ``hi_f`` of every numeric feature, in one pass."""
    return entries.agg(*(x for f in features for x in (F.min(f).alias(f"lo_{f}"), F.max(f).alias(f"hi_{f}"))))


def out_of_range(entries: DataFrame, pinned: dict[str, tuple[int, int]]) -> DataFrame:
    """(feature, below, above, missing) of values that pinned bounds would clamp."""
    parts = [
        entries.agg(
            F.lit(f).alias("feature"),
            F.count_if(F.col(f) < lo).alias("below"),
            F.count_if(F.col(f) > hi).alias("above"),
            F.count_if(F.col(f).isNull()).alias("missing"),
        )
        for f, (lo, hi) in pinned.items()
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
