"""Summaries of a growing log: merging across batches with fixed numeric bounds."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, Window, functions as F

from repsum.operators.features import frequencies, with_domain
from repsum.operators.greedy import GAMMA, Pick, Result, compress
from repsum.operators.partitioned import _local
from repsum.plans.ranks import positions
from repsum.plans.scratch import materialise


def batches(entries: DataFrame, n: int, order: list[str]) -> DataFrame:
    """(qid, batch): equal consecutive runs, the first ones a row longer; ranks come from ranges, not from one task."""
    narrow = entries.select("qid", *(c for c in order if c != "qid")).withColumn("all", F.lit(0))
    ranked = materialise(positions(narrow, ["all"], order, "at"), "ranked")
    total = ranked.count()
    size, longer = divmod(total, n)
    head = longer * (size + 1)
    late = F.lit(longer) + (F.expr(f"(at - {head}) div {size}") if size else F.lit(0))
    return ranked.select("qid", (F.when(F.col("at") < head, F.expr(f"at div {size + 1}")).otherwise(late) + 1).cast("int").alias("batch"))


def batches_by_range(entries: DataFrame, n: int, column: str) -> DataFrame:
    """(qid, batch) by approximate quantiles of a column: the form for logs too large for one ordering task."""
    cuts = entries.approxQuantile(column, [i / n for i in range(1, n)], 0.001)
    number = F.lit(1)
    for c in cuts:
        number = number + F.when(F.col(column) > c, 1).otherwise(0)
    return entries.select("qid", number.alias("batch"))


def merge_append(a: DataFrame, b: DataFrame) -> DataFrame:
    """Multiset sum of two summaries, or of two token tables."""
    return a.unionByName(b)


def merge_counts(a: DataFrame, b: DataFrame) -> DataFrame:
    """(feature, token, freq) of two batches together."""
    return a.unionByName(b).groupBy("feature", "token").agg(F.sum("freq").alias("freq"))


def merge_compress(a: list[Pick], b: list[Pick], budget: float, d: np.ndarray, gamma=GAMMA, unit: bool = True) -> Result:
    """Greedy over two summaries, shrunk to the budget."""
    return _local([*a, *b], d, budget, unit, gamma)


def merge_bounds(both_a: DataFrame, both_b: DataFrame, both_union: DataFrame, sizes: tuple[int, int, int, int]) -> DataFrame:
    """One row: what the merge of two summaries guarantees and what it has.

    alpha_min of the merge is at least half the smaller of the two. rho_linf is at least the
    smaller of the two only if the summaries are as large as their logs are to each other;
    ``sizes`` are the token counts of S, S', W and W'.
    """
    from repsum.operators.metrics import coverage, representativity

    def score(both: DataFrame, tag: str) -> DataFrame:
        return coverage(both).crossJoin(representativity(both)).select(F.col("alpha_min").alias(f"alpha_{tag}"), F.col("rho_linf").alias(f"rho_{tag}"))

    s, s2, w, w2 = sizes
    row = score(both_a, "a").crossJoin(score(both_b, "b")).crossJoin(score(both_union, "ab"))
    return row.select("*", (F.least("alpha_a", "alpha_b") / 2).alias("alpha_bound"), F.least("rho_a", "rho_b").alias("rho_bound"), F.lit(s * w2 == s2 * w).alias("proportional"))


def prefix_targets(toks: DataFrame, dom: DataFrame, batch_of: DataFrame, n: int, size: int) -> list[np.ndarray]:
    """Shares of the log up to each batch, by tid: what each batch's target is without looking ahead.

    One pass counts every batch; n rows per token of a checked domain reach the driver.
    """
    per = with_domain(toks.join(batch_of, "qid"), dom.select("tid", "feature", "token")).groupBy("batch", "tid").agg(F.sum("mult").alias("freq")).toPandas()
    counts = np.zeros((n, size))
    counts[per["batch"].to_numpy(int) - 1, per["tid"].to_numpy(int)] = per["freq"].to_numpy(float)
    upto = counts.cumsum(axis=0)
    return list(upto / np.maximum(upto.sum(axis=1, keepdims=True), 1))


def run_incremental(vectors: DataFrame, batch_of: DataFrame, targets: list[np.ndarray], budget_of, gamma=GAMMA, scratch: bool = True) -> list[dict]:
    """Add batches one at a time; ``targets`` has the target after each, ``budget_of(entries so far)`` is the number of picks.

    Returns, per batch, the merged result with its seconds and entries looked at so far; and, if
    ``scratch``, the same of a run over all entries up to the batch under the same target.
    """
    held: list[Pick] = []
    out, seen, looked, afresh = [], 0, 0, 0
    took = {"merged": 0.0, "scratch": 0.0}
    tagged = materialise(vectors.join(batch_of, "qid"), "tagged")
    sizes = {r["batch"]: r["count"] for r in tagged.groupBy("batch").count().collect()}
    for b, d in enumerate(targets, 1):
        seen += sizes.get(b, 0)
        looked, afresh, k = looked + sizes.get(b, 0), afresh + seen, budget_of(seen)
        began = time.perf_counter()
        new = compress(tagged.where(F.col("batch") == b).drop("batch"), d, min(k, sizes.get(b, 0)), gamma)
        merged = merge_compress(held, new.picks, k, d, gamma)
        took["merged"] += time.perf_counter() - began
        held = merged.picks
        row = {"batch": b, "entries": seen, "looked_at": looked, "scratch_looked_at": afresh, "result": merged, "seconds": took["merged"], "target": d}
        if scratch:
            began = time.perf_counter()
            row["scratch"] = compress(tagged.where(F.col("batch") <= b).drop("batch"), d, k, gamma)
            took["scratch"] += time.perf_counter() - began
            row["scratch_seconds"] = took["scratch"]
        out.append(row)
    return out


def daily_drift(toks: DataFrame, day_of: DataFrame) -> DataFrame:
    """(day, tv, n_new, n_gone): each day's token shares against the day before."""
    daily = toks.join(day_of.select("qid", "day"), "qid").groupBy("day", "feature", "token").agg(F.sum("mult").alias("freq"))
    shares = daily.withColumn("p", F.col("freq") / F.sum("freq").over(Window.partitionBy("day")))
    days = daily.select("day").distinct().withColumn("before", F.lag("day").over(Window.orderBy("day"))).where("before is not null")  # one row per day
    now = shares.join(F.broadcast(days), "day").select(F.col("day").alias("d"), "feature", "token", "p", F.lit(1).alias("n"))
    last = shares.select(F.col("day").alias("before"), "feature", "token", F.col("p").alias("p0")).join(F.broadcast(days), "before").select(F.col("day").alias("d"), "feature", "token", "p0")
    both = now.join(last, ["d", "feature", "token"], "full_outer")
    return both.groupBy(F.col("d").alias("day")).agg((F.sum(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("p0", F.lit(0.0)))) / 2).alias("tv"), F.count_if(F.col("p0").isNull()).alias("n_new"), F.count_if(F.col("p").isNull()).alias("n_gone"))


def running_target(toks: DataFrame, batch_of: DataFrame) -> DataFrame:
    """(batch, feature, token, freq): counts of all batches up to each one."""
    per = toks.join(batch_of, "qid").groupBy("batch", "feature", "token").agg(F.sum("mult").alias("freq"))
    later = batch_of.select(F.col("batch").alias("upto")).distinct()  # one row per batch
    return per.join(F.broadcast(later), F.col("batch") <= F.col("upto")).groupBy(F.col("upto").alias("batch"), "feature", "token").agg(F.sum("freq").alias("freq"))


__all__ = ["batches", "batches_by_range", "daily_drift", "frequencies", "merge_append", "merge_bounds", "merge_compress", "merge_counts", "run_incremental", "running_target"]
