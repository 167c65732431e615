"""Choosing the knobs: parameter sweeps, boosted token weights, test workloads by target."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window, functions as F

from repsum.operators import features, greedy
from repsum.plans.prepare import Prepared


def sweep(p: Prepared, gammas, betas, sizes) -> list[dict]:
    """Blended score of every (gamma, beta, size); one greedy run per gamma, since its prefixes nest."""
    kinds, out = p.features(), []
    for g in gammas:
        rows = greedy.trace(greedy.compress(p.vectors, p.d, max(sizes), g), p.d, kinds, g)
        for r in rows:
            if r["pick_no"] in sizes:
                out += [{"gamma": str(g), "beta": b, "k": r["pick_no"], "score": b * r["alpha_avg"] + (1 - b) * r["rho_l1"]} for b in betas]
    return out


def best_setting(rows: list[dict], beta: float, k: int) -> dict:
    """The setting with the best score at one beta and size; the smaller gamma wins a tie."""
    return max((r for r in rows if r["beta"] == beta and r["k"] == k), key=lambda r: (r["score"], r["gamma"]))


def boost_weights(p: Prepared, k: int, rounds: int = 5, factor: float = 2.0, gamma=greedy.GAMMA) -> tuple[np.ndarray, list[dict]]:
    """Raise the target of tokens that the summary under-represents, round by round.

    Returns the weights of the round with the best representativity and what every round had.
    """
    weights = np.ones(len(p.d))
    best, history = (-1.0, weights), []
    for n in range(rounds):
        d = p.d * weights
        got = greedy.compress(p.vectors, d / d.sum(), k, gamma)
        m = np.zeros(len(d))
        for pick in got.picks:
            m[pick.tids] += pick.mults
        share = m / max(m.sum(), 1)
        rho = float(1 - np.abs(share - p.d).sum() / 2)
        history.append({"round": n, "rho_l1": rho, "covered": int((m > 0).sum())})
        if rho > best[0]:
            best = rho, weights.copy()
        weights = np.where(share < p.d, weights * factor, weights)
        weights /= weights.mean()
    return best[1], history


def uniform_target(toks: DataFrame) -> DataFrame:
    """Every token alike: the target of a test workload that exercises rare features."""
    return features.frequencies(toks).select("feature", "token", (1 / F.count("*").over(Window.partitionBy())).alias("d"))


def even_target(toks: DataFrame) -> DataFrame:
    """Every feature alike, and within a feature every token: large domains do not drown small ones."""
    freq = features.frequencies(toks)
    per = freq.groupBy("feature").agg(F.count("*").alias("n")).withColumn("kinds", F.count("*").over(Window.partitionBy()))  # a row per feature
    return freq.join(F.broadcast(per), "feature").select("feature", "token", (1 / (F.col("n") * F.col("kinds"))).alias("d"))


def boosted_target(toks: DataFrame, feature: str, factor: float) -> DataFrame:
    """The log's shares with one feature's multiplied by ``factor``."""
    raised = features.distribution(toks).withColumn("x", F.col("p") * F.when(F.col("feature") == feature, factor).otherwise(1.0))
    return raised.select("feature", "token", (F.col("x") / F.sum("x").over(Window.partitionBy())).alias("d"))
