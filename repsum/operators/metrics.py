"""Measures of a summary against its log, all over token tables of the two.

A summary without tokens scores 0 everywhere. Shares run over all features together unless a
measure says otherwise; ``target`` is (feature, token, d) and defaults to the log's own shares.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from repsum.operators.features import distribution, frequencies


def compare(toks_s: DataFrame, toks_w: DataFrame, target: DataFrame | None = None) -> DataFrame:
    """(feature, token, mw, ms, d, ps): both sides of every token of the log."""
    w = distribution(toks_w).select("feature", "token", F.col("freq").alias("mw"), F.col("p").alias("d"))
    if target is not None:
        given = target.select("feature", "token", F.col("d").alias("given"))
        w = w.join(given, ["feature", "token"], "left").select("feature", "token", "mw", F.coalesce("given", F.lit(0.0)).alias("d"))
    s = frequencies(toks_s).select("feature", "token", F.col("freq").alias("ms"))
    both = w.join(s, ["feature", "token"], "left").withColumn("ms", F.coalesce("ms", F.lit(0)))
    size = both.agg(F.sum("ms").alias("zs"))  # one row
    return both.crossJoin(F.broadcast(size)).withColumn("ps", F.when(F.col("zs") > 0, F.col("ms") / F.col("zs")).otherwise(0.0)).drop("zs")


def coverage_by_feature(both: DataFrame) -> DataFrame:
    return both.groupBy("feature").agg((F.count_if(F.col("ms") > 0) / F.count("*")).alias("alpha"))


def coverage(both: DataFrame) -> DataFrame:
    """One row: alpha_min, alpha_avg."""
    return coverage_by_feature(both).agg(F.min("alpha").alias("alpha_min"), F.avg("alpha").alias("alpha_avg"))


def _any(both_ms: str = "ms") -> Column:
    return F.sum(both_ms) > 0


def representativity(both: DataFrame) -> DataFrame:
    """One row: rho_l1 (one minus total variation) and rho_linf (one minus the largest gap)."""
    gap = F.abs(F.col("ps") - F.col("d"))
    return both.agg(F.when(_any(), 1 - F.sum(gap) / 2).otherwise(0.0).alias("rho_l1"), F.when(_any(), 1 - F.max(gap)).otherwise(0.0).alias("rho_linf"))


def scores_by_feature(both: DataFrame) -> DataFrame:
    """(feature, alpha, rho_l1, rho_linf) with shares within each feature."""
    sums = both.groupBy("feature").agg(F.sum("ms").alias("zs"), F.sum("d").alias("zd"))
    within = both.select("feature", "token", "ms", "d").join(F.broadcast(sums), "feature")  # one row per feature
    gap = F.abs(F.when(F.col("zs") > 0, F.col("ms") / F.col("zs")).otherwise(0.0) - F.col("d") / F.col("zd"))
    return within.groupBy("feature").agg(
        (F.count_if(F.col("ms") > 0) / F.count("*")).alias("alpha"),
        F.when(_any(), 1 - F.sum(gap) / 2).otherwise(0.0).alias("rho_l1"),
        F.when(_any(), 1 - F.max(gap)).otherwise(0.0).alias("rho_linf"),
    )


def weighted_scores(both: DataFrame, weights: DataFrame) -> DataFrame:
    """One row: alpha_w, rho_w from the per-feature scores and (feature, w)."""
    per = scores_by_feature(both).join(F.broadcast(weights.select("feature", "w")), "feature")
    return per.agg(F.sum(F.col("w") * F.col("alpha")).alias("alpha_w"), F.sum(F.col("w") * F.col("rho_l1")).alias("rho_w"))


def scores(both: DataFrame) -> DataFrame:
    """One row: alpha_min, alpha_avg, rho_l1, rho_linf."""
    return coverage(both).crossJoin(representativity(both))


def blend(row: DataFrame, beta: float) -> DataFrame:
    """The four blended scores beta * alpha + (1 - beta) * rho of a row of scores()."""
    mix = lambda a, r: (F.lit(beta) * F.col(a) + F.lit(1 - beta) * F.col(r))
    return row.select(
        F.lit(beta).alias("beta"),
        mix("alpha_min", "rho_l1").alias("min_l1"),
        mix("alpha_min", "rho_linf").alias("min_linf"),
        mix("alpha_avg", "rho_l1").alias("avg_l1"),
        mix("alpha_avg", "rho_linf").alias("avg_linf"),
    )


def compression_ratio(costs: DataFrame, picked: DataFrame) -> DataFrame:
    """One row: eta = 1 - c(S) / c(W), for ``costs`` (qid, cost) and ``picked`` (qid)."""
    flagged = costs.join(picked.select(F.col("qid").alias("picked_id")), F.col("qid") == F.col("picked_id"), "left")
    return flagged.agg((1 - F.coalesce(F.sum(F.when(F.col("picked_id").isNotNull(), F.col("cost"))), F.lit(0)) / F.sum("cost")).alias("eta"))


def objective(both: DataFrame, gamma: float) -> DataFrame:
    """One row: G = sum of d * ln((m + gamma) / gamma)."""
    return both.agg(F.sum(F.when(F.col("ms") > 0, F.col("d") * (F.log(F.col("ms") + F.lit(gamma)) - F.log(F.lit(gamma)))).otherwise(0.0)).alias("g"))


def objective_limit(both: DataFrame) -> DataFrame:
    """One row, to be compared in this order: target mass covered, and sum of d * ln m over what is covered."""
    hit = F.col("ms") > 0
    return both.agg(F.sum(F.when(hit, F.col("d")).otherwise(0.0)).alias("covered"), F.sum(F.when(hit, F.col("d") * F.log(F.col("ms").cast("double"))).otherwise(0.0)).alias("log_part"))


def divergence(both: DataFrame, smoothed: float | None = None) -> DataFrame:
    """One row: kl = KL(d || p_S) and entropy = H(d); infinite where S lacks a token and nothing is smoothed."""
    if smoothed is None:
        p = F.col("ps")
        rows = both
    else:
        total = both.agg(F.sum(F.col("ms") + F.lit(smoothed)).alias("zz"))
        rows = both.crossJoin(F.broadcast(total))
        p = (F.col("ms") + F.lit(smoothed)) / F.col("zz")
    term = F.when(F.col("d") == 0, 0.0).when(p == 0, F.lit(float("inf"))).otherwise(F.col("d") * (F.log("d") - F.log(p)))
    return rows.agg(F.sum(term).alias("kl"), F.sum(F.when(F.col("d") > 0, -F.col("d") * F.log("d")).otherwise(0.0)).alias("entropy"))


def drift(toks_a: DataFrame, toks_b: DataFrame) -> DataFrame:
    """One row: total variation between two token tables, and how many tokens are new or gone."""
    a = distribution(toks_a).select("feature", "token", F.col("p").alias("pa"))
    b = distribution(toks_b).select("feature", "token", F.col("p").alias("pb"))
    both = a.join(b, ["feature", "token"], "full_outer")
    return both.agg((F.sum(F.abs(F.coalesce("pa", F.lit(0.0)) - F.coalesce("pb", F.lit(0.0)))) / 2).alias("tv"), F.count_if(F.col("pa").isNull()).alias("n_new"), F.count_if(F.col("pb").isNull()).alias("n_gone"))
