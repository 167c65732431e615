from fractions import Fraction

import numpy as np
import pytest

from repsum.operators import baselines, linkage
from repsum.plans.scratch import ship_package


def exact(rows, k, kind):
    """Average linkage over one number and a set in exact arithmetic, ties to the smaller ids."""

    def dist(x, y):
        gap, a, b = abs(Fraction(x[1][0]) - Fraction(y[1][0])), set(x[2]), set(y[2])
        sets = 1 - Fraction(len(a & b), len(a | b)) if a | b else Fraction(0)
        return {"numeric": gap, "categorical": sets, "mixed": (gap + sets) / 2}[kind]

    d = [[dist(x, y) for y in rows] for x in rows]
    sums = {(i, j): d[i][j] for i in range(len(rows)) for j in range(i + 1, len(rows))}
    members = {i: [i] for i in range(len(rows))}
    while len(members) > k:
        _, a, b = min((s / (len(members[i]) * len(members[j])), i, j) for (i, j), s in sums.items())
        for x in members:
            if x not in (a, b):
                sums[min(a, x), max(a, x)] += sums.pop((min(b, x), max(b, x)))
        del sums[a, b]
        members[a] += members.pop(b)
    return sorted(rows[min(c, key=lambda i: (sum(d[i][j] for j in c), i))][0] for c in members.values())


@pytest.mark.parametrize("kind", ["numeric", "categorical", "mixed"])
@pytest.mark.parametrize("matrix", [1, 12, 1024])
def test_average_linkage_is_exact_at_any_length(spark, monkeypatch, kind, matrix):
    """Logs beyond a matrix, with many ties and equal entries, on the driver and in tasks, in tiles of any size."""
    ship_package(spark)
    rng = np.random.default_rng(11)
    rows = [(3 * q + 1, [float(rng.integers(0, 16)) / 8], [f"t{t}" for t in rng.integers(0, 6, int(rng.integers(0, 4)))]) for q in range(60)]
    df = spark.createDataFrame(rows[::-1], "qid long, num array<double>, toks array<string>").cache()
    monkeypatch.setattr(baselines, "MAX_PAIRWISE", 50)
    monkeypatch.setattr(linkage, "MATRIX", matrix)
    for k in (1, 4, 20, 50, 60):
        assert baselines.hierarchical(df, k, "average", kind) == exact(rows, k, kind)
    for name, small in (("ROWS", 7), ("COLUMNS", 13), ("TOKENS", 2), ("SUMS", 50), ("LOCAL_PAIRS", 0)):
        monkeypatch.setattr(linkage, name, small)
    assert baselines.hierarchical(df, 4, "average", kind) == exact(rows, 4, kind)


def test_average_linkage_of_few_entries(spark):
    df = spark.createDataFrame([(q, [0.5], ["a"]) for q in range(6)], "qid long, num array<double>, toks array<string>")
    assert baselines.hierarchical(df, 3, "average", "mixed") == [0, 4, 5]
    assert baselines.hierarchical(df, 9, "average", "mixed") == list(range(6))
    assert baselines.hierarchical(df.where("qid < 0"), 2, "average", "mixed") == []
