"""Distances between entries, as column expressions and as arrays for small samples."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, functions as F


def euclid(a: Column, b: Column) -> Column:
    """Euclidean distance of two arrays of doubles, over the root of their length."""
    squares = F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    return F.sqrt(squares / F.greatest(F.size(a), F.lit(1)))


def jaccard(a: Column, b: Column) -> Column:
    """1 - |A and B| / |A or B| of two arrays as sets; 0 for two empty sets."""
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, 0.0).otherwise(1 - F.size(F.array_intersect(a, b)) / union)


def mixed(num_a: Column, num_b: Column, set_a: Column, set_b: Column) -> Column:
    return (euclid(num_a, num_b) + jaccard(set_a, set_b)) / 2


def pairwise(num: np.ndarray | None, bags: list[dict] | None, multiset: bool = False) -> np.ndarray:
    """All distances of a small sample: numeric, categorical, or their mean where both are given."""
    parts = []
    if num is not None:
        gap = num[:, None, :] - num[None, :, :]
        parts.append(np.sqrt((gap**2).mean(axis=2)))
    if bags is not None:
        names = {t: i for i, t in enumerate(sorted({t for b in bags for t in b}))}
        table = np.zeros((len(bags), max(1, len(names))), np.float64)
        for r, b in enumerate(bags):
            for t, n in b.items():
                table[r, names[t]] = n if multiset else 1
        out = np.zeros((len(bags), len(bags)))
        for r in range(len(bags)):
            both = np.minimum(table, table[r]).sum(1)
            either = np.maximum(table, table[r]).sum(1)
            out[r] = np.where(either > 0, 1 - both / np.where(either > 0, either, 1), 0.0)
        parts.append(out)
    return sum(parts) / len(parts)
