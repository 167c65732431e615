"""Registered queries of the engine: one per method, variant, baseline, measure and operator."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from repsum.functions import numeric
from repsum.functions.sqltext import fingerprint, join_counts, register, sql_tokens
from repsum.operators import advisor, baselines, features, greedy, incremental, metrics, partitioned, tuning
from repsum.plans.oracle import BETAS, GAMMAS, PINNED, WEIGHTS
from repsum.plans.prepare import Prepared, prepare, sqrt_budget, views
from repsum.plans.scratch import materialise, ship_package
from repsum.sources import logs, templates
from repsum.sources.tables import cents, read

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}


def query(f: Query) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship_package(spark)
        return f(spark, sf_dir)

    QUERIES[f.__name__] = run
    return f


def _rounded(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in columns})


def _orders(spark: SparkSession, sf_dir: str, **options) -> Prepared:
    return prepare(logs.orders_log(spark, sf_dir), **options)


def _weights(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(WEIGHTS.items()), "feature string, w double")


# logs and features


@query
def w_orders_tokens(spark, sf_dir):
    return features.tokens(logs.orders_log(spark, sf_dir))


@query
def w_orders_numeric(spark, sf_dir):
    return logs.orders_log(spark, sf_dir).entries.select("qid", "n1", "n2", "n3", "n4", "n5", "n6")


@query
def w_events_tokens(spark, sf_dir):
    return features.tokens(logs.events_log(spark, sf_dir))


@query
def w_docs_tokens(spark, sf_dir):
    return features.domain_advice(features.frequencies(logs.docs_log(spark, sf_dir).bags))


@query
def w_conv_tokens(spark, sf_dir):
    return logs.conversations_log(spark, sf_dir).bags


@query
def w_pages_tokens(spark, sf_dir):
    return logs.pages_log(spark, sf_dir).bags


@query
def w_sql_tokens(spark, sf_dir):
    return sql_tokens(templates.order_log(spark, sf_dir, templates.REPORTS))


@query
def w_star_tokens(spark, sf_dir):
    return sql_tokens(templates.order_log(spark, sf_dir, templates.STARS))


@query
def w_sql_odd_tokens(spark, sf_dir):
    """Texts with ordinals, aliases, expressions, quoted names, comments and lists of literals."""
    return sql_tokens(templates.odd_order_log(spark, sf_dir))


@query
def w_sql_mix_tokens(spark, sf_dir):
    """The mixed log of both sets of templates, at the orders table's length."""
    log = templates.mixed_log(spark, read(spark, sf_dir, "orders").count())
    return sql_tokens(log).groupBy("feature", "token").agg(F.sum("mult").alias("freq"))


@query
def w_sql_where(spark, sf_dir):
    return sql_tokens(templates.order_log(spark, sf_dir, templates.STARS), ("where_column",)).groupBy("token").agg(F.sum("mult").alias("freq"))


@query
def w_sql_statistics(spark, sf_dir):
    """How many different statistics and literals the modelled logs have, per template."""
    log = templates.order_log(spark, sf_dir, templates.REPORTS)
    return log.groupBy("template").agg(F.count_distinct("sql").alias("texts"), F.count_distinct("exec_ms").alias("times"), F.min("n_joins").alias("n_joins"))


@query
def doc_words(spark, sf_dir):
    return features.frequencies(logs.docs_log(spark, sf_dir).bags)


@query
def token_map(spark, sf_dir):
    """Bags as maps: occurrences by feature of each entry, looked up by name."""
    per = features.tokens(logs.orders_log(spark, sf_dir)).groupBy("qid", "feature").agg(F.sum("mult").alias("n"))
    bags = per.groupBy("qid").agg(F.map_from_entries(F.collect_list(F.struct("feature", "n"))).alias("bag"))
    return bags.select("qid", *(F.coalesce(F.element_at("bag", f), F.lit(0)).alias(f) for f in ("fn", "tb", "ob")), F.size("bag").alias("features"))


@query
def w_sql_joins(spark, sf_dir):
    return join_counts(templates.order_log(spark, sf_dir, templates.REPORTS))


@query
def w_sql_fingerprints(spark, sf_dir):
    log = templates.order_log(spark, sf_dir, templates.REPORTS + templates.STARS)
    return log.select("template", fingerprint(F.col("sql")).alias("fingerprint")).groupBy("template", "fingerprint").agg(F.count("*").alias("n"))


@query
def bounds(spark, sf_dir):
    log = logs.orders_log(spark, sf_dir)
    row = numeric.bounds(log.entries, log.numeric)
    return row.select(F.explode(F.array(*(F.struct(F.lit(f).alias("feature"), F.col(f"lo_{f}").alias("lo"), F.col(f"hi_{f}").alias("hi")) for f in log.numeric))).alias("x")).select("x.*")


def _buckets(h, pinned=None):
    def run(spark, sf_dir):
        log = logs.orders_log(spark, sf_dir)
        return features.numeric_tokens(log.entries, log.numeric, h, pinned).groupBy("feature", "token").agg(F.count("*").alias("n"))

    return run


for _name, _run in (("buckets_h10", _buckets(10)), ("buckets_h1000", _buckets(1000)), ("buckets_pinned", _buckets(1000, PINNED))):
    _run.__name__ = _name
    query(_run)


@query
def out_of_range(spark, sf_dir):
    return numeric.out_of_range(logs.orders_log(spark, sf_dir).entries, PINNED)


@query
def token_freq(spark, sf_dir):
    return _rounded(features.distribution(features.tokens(logs.orders_log(spark, sf_dir))), "p", digits=9)


@query
def domain_sizes(spark, sf_dir):
    return features.domain_advice(features.frequencies(features.tokens(logs.orders_log(spark, sf_dir)))).drop("advice")


@query
def query_sizes(spark, sf_dir):
    return features.query_sizes(features.tokens(logs.orders_log(spark, sf_dir)))


@query
def packed_vectors(spark, sf_dir):
    v = _orders(spark, sf_dir).vectors
    return v.select("qid", F.array_join(F.zip_with("tids", "mults", lambda t, m: F.concat_ws(":", t, m)), ",").alias("vec"))


@query
def cross_feature(spark, sf_dir):
    return features.cross_feature(features.tokens(logs.orders_log(spark, sf_dir)), "fn", "ob")


@query
def feature_corr(spark, sf_dir):
    log = logs.orders_log(spark, sf_dir)
    return _rounded(features.numeric_correlation(log.entries, log.numeric), "r")


@query
def cramers_v(spark, sf_dir):
    return _rounded(features.cramers_v(read(spark, sf_dir, "orders"), "o_orderstatus", "o_orderpriority"), "v")


@query
def inverse_domain_weights(spark, sf_dir):
    return _rounded(features.inverse_domain_weights(features.frequencies(features.tokens(logs.orders_log(spark, sf_dir)))), "w", digits=9)


# measures of a seeded sample of sqrt(n) entries


def _sampled(spark, sf_dir, target: DataFrame | None = None):
    log = logs.orders_log(spark, sf_dir)
    toks = materialise(features.tokens(log), "tokens")
    sample = baselines.random_sample(log.entries, sqrt_budget(log.entries))
    own = toks.join(F.broadcast(sample), "qid", "left_semi")
    return toks, sample, metrics.compare(own, toks, target)


@query
def coverage_by_feature(spark, sf_dir):
    return _rounded(metrics.coverage_by_feature(_sampled(spark, sf_dir)[2]), "alpha")


@query
def coverage_min_avg(spark, sf_dir):
    return _rounded(metrics.coverage(_sampled(spark, sf_dir)[2]), "alpha_min", "alpha_avg")


@query
def rho_l1(spark, sf_dir):
    return _rounded(metrics.representativity(_sampled(spark, sf_dir)[2]).select("rho_l1"), "rho_l1")


@query
def rho_linf(spark, sf_dir):
    return _rounded(metrics.representativity(_sampled(spark, sf_dir)[2]).select("rho_linf"), "rho_linf")


@query
def scores_by_feature(spark, sf_dir):
    return _rounded(metrics.scores_by_feature(_sampled(spark, sf_dir)[2]), "alpha", "rho_l1", "rho_linf")


@query
def scores_weighted(spark, sf_dir):
    return _rounded(metrics.weighted_scores(_sampled(spark, sf_dir)[2], _weights(spark)), "alpha_w", "rho_w")


_uniform = tuning.uniform_target


@query
def scores_custom_target(spark, sf_dir):
    toks = features.tokens(logs.orders_log(spark, sf_dir))
    return _rounded(metrics.representativity(_sampled(spark, sf_dir, _uniform(toks))[2]), "rho_l1", "rho_linf")


@query
def blend_grid(spark, sf_dir):
    row = materialise(metrics.scores(_sampled(spark, sf_dir)[2]), "scores")
    out = metrics.blend(row, BETAS[0])
    for b in BETAS[1:]:
        out = out.unionByName(metrics.blend(row, b))
    return _rounded(out, "min_l1", "min_linf", "avg_l1", "avg_linf")


@query
def compression_ratio(spark, sf_dir):
    toks, sample, _ = _sampled(spark, sf_dir)
    costs = features.query_sizes(toks).select("qid", F.col("size").alias("cost"))
    return _rounded(metrics.compression_ratio(costs, sample), "eta")


@query
def objective_gamma_grid(spark, sf_dir):
    both = materialise(_sampled(spark, sf_dir)[2], "both")
    out = None
    for g in GAMMAS:
        row = metrics.objective(both, g).select(F.lit(g).alias("gamma"), F.round("g", 6).alias("g"))
        out = row if out is None else out.unionByName(row)
    return out


@query
def objective_limit(spark, sf_dir):
    return _rounded(metrics.objective_limit(_sampled(spark, sf_dir)[2]), "covered", "log_part")


@query
def kl_entropy(spark, sf_dir):
    return _rounded(metrics.divergence(_sampled(spark, sf_dir)[2], smoothed=0.001), "kl", "entropy")


@query
def uncovered_tokens(spark, sf_dir):
    return _sampled(spark, sf_dir)[2].where("ms = 0").select("feature", "token", F.col("mw").alias("freq"))


@query
def toy_scores(spark, sf_dir):
    toks = materialise(logs.toy_tokens(spark), "toy")
    out = None
    for s in ([1], [2], [3], [1, 2], [1, 3], [2, 3], [1, 2, 3]):
        both = metrics.compare(toks.where(F.col("qid").isin(s)), toks)
        row = metrics.scores(both).crossJoin(metrics.objective(both, 1.0)).select(F.lit(",".join(map(str, s))).alias("s"), *(F.round(c, 6).alias(c) for c in ("alpha_min", "alpha_avg", "rho_l1", "rho_linf", "g")))
        out = row if out is None else out.unionByName(row)
    return out


# the compressor


def _eight(p: Prepared, gamma=greedy.GAMMA, **options) -> DataFrame:
    got = greedy.compress(p.vectors, p.d, options.pop("budget", 8), gamma, **options)
    return _rounded(greedy.summary(p.vectors.sparkSession, got), "gain")


@query
def greedy_unit_8(spark, sf_dir):
    return _eight(_orders(spark, sf_dir), strategy="eager")


@query
def greedy_fenced_eq_eager(spark, sf_dir):
    return _eight(_orders(spark, sf_dir), strategy="fenced", pool=500)


@query
def greedy_gamma1_8(spark, sf_dir):
    return _eight(_orders(spark, sf_dir), 1.0)


@query
def greedy_limit_8(spark, sf_dir):
    return _eight(_orders(spark, sf_dir), "limit")


@query
def greedy_knapsack_8(spark, sf_dir):
    return _eight(_orders(spark, sf_dir, size_cost=True), budget=200, unit=False, safeguard=False, most=8)


@query
def greedy_weighted_8(spark, sf_dir):
    return _eight(_orders(spark, sf_dir, weights=_weights(spark)))


@query
def greedy_target_8(spark, sf_dir):
    log = logs.orders_log(spark, sf_dir)
    return _eight(prepare(log, target=_uniform(features.tokens(log))))


@query
def testgen_uniform_8(spark, sf_dir):
    """A test workload in which every feature counts alike, and within it rare tokens as much as frequent ones."""
    log = logs.orders_log(spark, sf_dir)
    return _eight(prepare(log, target=tuning.even_target(features.tokens(log))))


@query
def greedy_events_8(spark, sf_dir):
    return _eight(prepare(logs.events_log(spark, sf_dir)))


@query
def greedy_best_singleton(spark, sf_dir):
    return _eight(_orders(spark, sf_dir), budget=1)


@query
def greedy_safeguard(spark, sf_dir):
    """The best single entry costs the whole budget, every other one 0.6 of it: density prefers those, the safeguard does not."""
    p = _orders(spark, sf_dir)
    best = greedy.compress(p.vectors, p.d, 1).picks[0].qid
    priced = p.vectors.withColumn("cost", F.when(F.col("qid") == best, 100.0).otherwise(60.0))
    return _rounded(greedy.summary(spark, greedy.compress(priced, p.d, 100, unit=False)), "gain")


@query
def greedy_collapsed_8(spark, sf_dir):
    """Equal entries collapsed to as many copies as there are picks: the same summary from fewer rows."""
    p = _orders(spark, sf_dir)
    p.vectors = materialise(greedy.collapse(p.vectors, 8), "collapsed")
    return _eight(p)


@query
def greedy_by_join_8(spark, sf_dir):
    """Greedy whose domain is never shipped or collected."""
    toks = materialise(features.tokens(logs.orders_log(spark, sf_dir)), "tokens")
    target = materialise(features.distribution(toks).select("feature", "token", F.col("p").alias("d")), "target")
    return _rounded(greedy.compress_by_join(toks, target, 8), "gain").withColumn("cost", F.lit(1.0))


@query
def greedy_trace_8(spark, sf_dir):
    p = _orders(spark, sf_dir)
    got = greedy.compress(p.vectors, p.d, 8)
    rows = greedy.trace(got, p.d, p.features(), greedy.GAMMA)
    return _rounded(spark.createDataFrame([tuple(r.values()) for r in rows], greedy.TRACE), "gain", "g", "alpha_min", "alpha_avg", "rho_l1", "rho_linf", "score")


@query
def greedy_best_prefix(spark, sf_dir):
    """The prefix of the summary with the best blended score, and the smallest that reaches nine tenths of it."""
    p = _orders(spark, sf_dir)
    rows = greedy.trace(greedy.compress(p.vectors, p.d, sqrt_budget(p.log.entries)), p.d, p.features(), greedy.GAMMA)
    best = greedy.best_prefix(rows)
    goal = 0.9 * rows[best - 1]["score"] if best else 0.0
    return spark.createDataFrame([(best, greedy.size_for(rows, goal), goal)], "best_prefix int, size_for_score int, score double")


@query
def platform_choice(spark, sf_dir):
    """A summary by numeric features alone, for choosing hardware: what queries cost, not what they say."""
    log = logs.orders_log(spark, sf_dir)
    return _eight(prepare(features.Log(log.entries, log.bags.where("false"), log.numeric)))


@query
def exhaustive_toy(spark, sf_dir):
    """The best summary of the worked example by size, every subset tried; greedy's beside it."""
    toks = materialise(logs.toy_tokens(spark), "toy")
    out = None
    for k, sets in ((1, ([1], [2], [3])), (2, ([1, 2], [1, 3], [2, 3])), (3, ([1, 2, 3],))):
        for some in sets:
            row = metrics.objective(metrics.compare(toks.where(F.col("qid").isin(some)), toks), 1.0).select(F.lit(k).alias("k"), F.lit(",".join(map(str, some))).alias("s"), F.round("g", 6).alias("g"))
            out = row if out is None else out.unionByName(row)
    best = out.groupBy("k").agg(F.max(F.struct("g", "s")).alias("b"))
    return best.select("k", F.col("b.s").alias("s"), F.col("b.g").alias("g"))


@query
def tuning_grid(spark, sf_dir):
    """Blended score by smoothing, blend and size, and which setting is best at each blend and size."""
    rows = tuning.sweep(_orders(spark, sf_dir), (1.0, 1e-10, 1e-25), (0.0, 0.5, 1.0), (10, 50))
    best = {(b, k): tuning.best_setting(rows, b, k)["gamma"] for b in (0.0, 0.5, 1.0) for k in (10, 50)}
    return spark.createDataFrame([(r["gamma"], r["beta"], r["k"], r["score"], best[r["beta"], r["k"]] == r["gamma"]) for r in rows], "gamma string, beta double, k int, score double, best boolean")


@query
def greedy_sqrt(spark, sf_dir):
    """The default compressor: a summary of sqrt(n) entries with the scores of every prefix."""
    p = _orders(spark, sf_dir)
    got = greedy.compress(p.vectors, p.d, sqrt_budget(p.log.entries))
    rows = greedy.trace(got, p.d, p.features(), greedy.GAMMA)
    return spark.createDataFrame([tuple(r.values()) for r in rows], greedy.TRACE)


def _priced(spark, sf_dir):
    """The orders log at the price of each order, and a cap of 0.2 % of them all."""
    p = prepare(logs.orders_log(spark, sf_dir), cost="n1")
    return p, p.blocks.total_cost() * 0.002


@query
def compliance_benchmark(spark, sf_dir):
    """Every kind of query within a cap on summed price, the cost of an order: knapsack with the safeguard."""
    p, cap = _priced(spark, sf_dir)
    return _rounded(greedy.summary(spark, greedy.compress(p.blocks, p.d, cap, "limit", unit=False)), "gain")


@query
def capped_vs_sample(spark, sf_dir):
    """The capped summary's scores against a random sample that spends no more than the same cap."""
    p, cap = _priced(spark, sf_dir)
    ids = {
        "greedy_limit": greedy.compress(p.blocks, p.d, cap, "limit", unit=False).ids(),
        "greedy": greedy.compress(p.blocks, p.d, cap, unit=False).ids(),
        "sample": baselines.sample_knapsack(p.vectors, cap),
    }
    return _method_scores(p, ids)


#: The smoothings of the published trade-off.
TRADE_OFF = (1.0, 1e-3, 1e-10, 1e-15, 1e-20, 1e-25)


@query
def gamma_sweep(spark, sf_dir):
    """Scores of summaries by smoothing and size; greedy prefixes nest, so one run serves all sizes."""
    p = _orders(spark, sf_dir)
    kinds, sizes = p.features(), (25, 50, 100, 200, 400)
    out = []
    for g in (*TRADE_OFF, "limit"):
        rows = greedy.trace(greedy.compress(p.blocks, p.d, max(sizes), g), p.d, kinds, g)
        out += [(str(g), r["pick_no"], r["alpha_avg"], r["rho_l1"], r["score"]) for r in rows if r["pick_no"] in sizes]
    return spark.createDataFrame(out, "gamma string, k int, alpha_avg double, rho_l1 double, score double")


@query
def gamma_by_feature(spark, sf_dir):
    """Coverage and representativity of each feature by smoothing, at the default size."""
    p = _orders(spark, sf_dir)
    kinds, number, k = p.kinds(), p.features(), sqrt_budget(read(spark, sf_dir, "orders"))  # an entry an order
    out = [(str(g), *row) for g in TRADE_OFF for row in greedy.feature_scores(greedy.compress(p.blocks, p.d, k, g).picks, p.d, number, kinds)]
    return spark.createDataFrame(out, "gamma string, feature string, alpha double, rho_l1 double")


@query
def feature_scores_8(spark, sf_dir):
    """Coverage and representativity of each feature after eight picks."""
    p = _orders(spark, sf_dir)
    got = greedy.feature_scores(greedy.compress(p.vectors, p.d, 8).picks, p.d, p.features(), p.kinds())
    return _rounded(spark.createDataFrame(got, "feature string, alpha double, rho_l1 double"), "alpha", "rho_l1")


@query
def gains_by_join(spark, sf_dir):
    """First-round gains without shipping the domain: the pass for domains beyond a broadcast."""
    toks = features.tokens(logs.orders_log(spark, sf_dir))
    target = features.distribution(toks).select("feature", "token", F.col("p").alias("d"))
    state = target.select("feature", "token", F.lit(0).alias("m"))
    return greedy.gains_by_join(toks, target, state, 1e-25).select("qid", F.round("gain", 6).alias("gain"))


# parts and batches


@query
def partition_sizes(spark, sf_dir):
    return logs.orders_log(spark, sf_dir).entries.groupBy(partitioned.part_of(3).alias("part")).agg(F.count("*").alias("n"))


def _part_picks(k):
    def run(spark, sf_dir):
        p = _orders(spark, sf_dir)
        local = partitioned.local_summaries(p.vectors, p.d, 3, 3)
        return local.where(F.col("part") == k).select("pick_no", "qid", F.round("gain", 6).alias("gain"), "cost")

    return run


for _k in range(3):
    _run = _part_picks(_k)
    _run.__name__ = f"partition_{_k}_picks"
    query(_run)


@query
def partition_merge(spark, sf_dir):
    p = _orders(spark, sf_dir)
    return _rounded(greedy.summary(spark, partitioned.compress_partitioned(p.vectors, p.d, 20, 4)), "gain")


@query
def partition_merge_4(spark, sf_dir):
    """Three parts of four picks each, and four picks of their union."""
    p = _orders(spark, sf_dir)
    return _rounded(greedy.summary(spark, partitioned.compress_partitioned(p.vectors, p.d, 4, 3)), "gain")


@query
def partition_shares(spark, sf_dir):
    """What partitioning costs: the share of one part's value that is kept by parts, by as many parts as picks, by a tree, and by parts with targets of their own."""
    p, k = _orders(spark, sf_dir), 40
    whole = greedy.value(p.d, greedy.compress(p.blocks, p.d, k).picks, greedy.GAMMA)
    runs = {f"{n} parts": {"parts": n} for n in (1, 2, 4, 6)} | {"as many parts as picks": {"parts": "budget"}, "tree of 16": {"parts": 16, "levels": 2, "fan": 4}, "4 parts, own targets": {"parts": 4, "scope": "local"}}
    out = []
    for name, how in runs.items():
        picks = partitioned.compress_partitioned(p.blocks, p.d, k, **how).picks
        row = greedy.trace(greedy.Result(picks), p.d, p.features(), greedy.GAMMA)[-1]
        out.append((name, len(picks), greedy.value(p.d, picks, greedy.GAMMA) / whole, row["alpha_avg"], row["rho_l1"]))
    return spark.createDataFrame(out, "how string, picks int, share double, alpha_avg double, rho_l1 double")


@query
def partition_tree(spark, sf_dir):
    p = _orders(spark, sf_dir)
    return _rounded(greedy.summary(spark, partitioned.compress_partitioned(p.vectors, p.d, 20, 16, levels=2, fan=4)), "gain")


def _batches(spark, sf_dir, n: int = 7):
    log = logs.events_log(spark, sf_dir)
    return log, incremental.batches(log.entries, n, ["ts", "qid"])


@query
def batch_ntile(spark, sf_dir):
    _, b = _batches(spark, sf_dir)
    return b.groupBy("batch").agg(F.count("*").alias("n"), F.min("qid").alias("first_qid"), F.max("qid").alias("last_qid"))


@query
def running_target(spark, sf_dir):
    log, b = _batches(spark, sf_dir)
    return incremental.running_target(features.tokens(log), b)


@query
def merge_append(spark, sf_dir):
    log, b = _batches(spark, sf_dir)
    tagged = materialise(features.tokens(log).join(b, "qid"), "tagged")
    return reduce(incremental.merge_counts, (features.frequencies(tagged.where(F.col("batch") == n)) for n in range(1, 8)))


@query
def merge_bounds(spark, sf_dir):
    log, b = _batches(spark, sf_dir, 2)
    toks = materialise(features.tokens(log), "tokens")
    tagged = materialise(toks.join(b, "qid"), "tagged")
    halves = [tagged.where(F.col("batch") == n).drop("batch") for n in (1, 2)]
    picks = [baselines.random_sample(h.select("qid").distinct(), 50) for h in halves]
    own = [h.join(F.broadcast(s), "qid", "left_semi") for h, s in zip(halves, picks)]
    size = [int(t.agg(F.sum("mult")).head()[0]) for t in (*own, *halves)]
    both = [metrics.compare(s, w) for s, w in zip(own, halves)]
    row = incremental.merge_bounds(both[0], both[1], metrics.compare(incremental.merge_append(*own), toks), tuple(size))
    return _rounded(row, "alpha_a", "rho_a", "alpha_b", "rho_b", "alpha_ab", "rho_ab", "alpha_bound", "rho_bound")


#: Numeric bounds of the events log, known before its batches arrive.
PINNED_EVENTS = {"value": (0, 60_000), "k": (0, 99), "gap": (0, 7 * 86_400_000), "run": (1, 50)}


def _increments(spark, sf_dir, scratch: bool):
    """Steps of seven batches with pinned bounds, each under the target of the log up to it, so nothing is known beforehand."""
    log, b = _batches(spark, sf_dir)
    b = materialise(b, "batches")
    p = prepare(log, pinned=PINNED_EVENTS)
    targets = incremental.prefix_targets(p.tokens, p.domain, b, 7, len(p.d))
    kinds = p.features()
    for s in incremental.run_incremental(p.vectors, b, targets, math.isqrt, scratch=scratch):
        yield s, greedy.trace(s["result"], s["target"], kinds, greedy.GAMMA)[-1], greedy.trace(s["scratch"], s["target"], kinds, greedy.GAMMA)[-1] if scratch else None


@query
def incremental_batches(spark, sf_dir):
    """Seven batches added one at a time: entries looked at, and the scores of the merged summary under each batch's target."""
    out = [(s["batch"], s["entries"], s["looked_at"], len(s["result"].picks), m["alpha_avg"], m["rho_l1"], m["score"]) for s, m, _ in _increments(spark, sf_dir, False)]
    return spark.createDataFrame(out, "batch int, entries long, looked_at long, picks int, alpha_avg double, rho_l1 double, score double")


@query
def increments_vs_scratch(spark, sf_dir):
    """The same batches, each against a run from scratch over the log up to it under the same target."""
    out = [(s["batch"], s["looked_at"], s["scratch_looked_at"], m["g"] / z["g"], m["score"], z["score"]) for s, m, z in _increments(spark, sf_dir, True)]
    return spark.createDataFrame(out, "batch int, looked_at long, scratch_looked_at long, share_of_scratch double, score double, scratch_score double")


@query
def drift_tv(spark, sf_dir):
    log = logs.events_log(spark, sf_dir)
    day = log.entries.select("qid", F.to_date("ts").alias("day"))
    return _rounded(incremental.daily_drift(log.bags, day), "tv")


# baselines


@query
def random_sample(spark, sf_dir):
    return baselines.random_sample(logs.orders_log(spark, sf_dir).entries, 100)


@query
def sample_knapsack(spark, sf_dir):
    costs = features.query_sizes(features.tokens(logs.orders_log(spark, sf_dir))).select("qid", F.col("size").alias("cost"))
    return baselines.sample_knapsack(costs, 1000)


@query
def sampling_curve(spark, sf_dir):
    log = logs.orders_log(spark, sf_dir)
    order = baselines.random_sample(log.entries, 100)
    toks = features.tokens(log).join(F.broadcast(order), "qid")
    ks = F.explode(F.filter(F.array(*map(F.lit, (10, 25, 50, 100))), lambda k: k >= F.col("pick_no"))).alias("k")
    return toks.select("feature", "token", "mult", ks).groupBy("k").agg(F.count_distinct("feature", "token").alias("covered"), F.sum("mult").alias("tokens"))


@query
def max_cover_8(spark, sf_dir):
    p = _orders(spark, sf_dir)
    got = greedy.compress(p.vectors, np.ones(len(p.d)), 8, "cover")
    return greedy.summary(spark, got).select("pick_no", "qid", F.col("gain").cast("long").alias("new_tokens"))


@query
def top_frequency(spark, sf_dir):
    same = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("qid"), F.array("text").alias("tids"), F.lit(1).alias("mults"))
    return baselines.top_frequency(same, 20)


@query
def medoid_assign(spark, sf_dir):
    p = logs.embeddings_log(spark, sf_dir)
    return _rounded(baselines.medoid_assign(p, p.where("qid < 8")), "dist")


@query
def medoid_update_1(spark, sf_dir):
    p = logs.embeddings_log(spark, sf_dir)
    return baselines.medoid_update(p, baselines.medoid_assign(p, p.where("qid < 8")))


def _chosen(points: DataFrame, k: int = 8) -> DataFrame:
    return points.join(F.broadcast(baselines.random_sample(points, k)), "qid", "left_semi")


@query
def euclid_to_chosen(spark, sf_dir):
    """Every vector of the table against eight entries by seeded hash."""
    p = logs.embeddings_log(spark, sf_dir).select("qid", "num")
    return _rounded(baselines.distances_to(p, _chosen(p)), "dist")


@query
def jaccard_to_chosen(spark, sf_dir):
    """Every entry of the orders log against eight entries by seeded hash; entries without tokens are empty sets."""
    log = logs.orders_log(spark, sf_dir)
    sets = features.tokens(log).groupBy("qid").agg(F.collect_set(F.concat_ws("=", "feature", "token")).alias("toks"))
    p = materialise(log.entries.select("qid").join(sets, "qid", "left").select("qid", F.coalesce("toks", F.array().cast("array<string>")).alias("toks")), "sets")
    return _rounded(baselines.distances_to(p, _chosen(p), "categorical"), "dist")


def _conversation_points(spark, sf_dir):
    log = logs.conversations_log(spark, sf_dir)
    return baselines.dense_points(log.entries, log.numeric, log.bags)


@query
def k_medoids_small(spark, sf_dir):
    ids, cost = baselines.k_medoids(_conversation_points(spark, sf_dir), 5, "mixed")
    return spark.createDataFrame([(i, round(cost, 6)) for i in ids], "qid long, cost double")


def _agglomerative(linkage):
    def run(spark, sf_dir):
        return spark.createDataFrame([(i,) for i in baselines.hierarchical(_conversation_points(spark, sf_dir), 5, linkage, "mixed")], "qid long")

    return run


for _name, _linkage in (("agglomerative_small", "average"), ("divisive_small", "divisive")):
    _run = _agglomerative(_linkage)
    _run.__name__ = _name
    query(_run)


@query
def doubling_small(spark, sf_dir):
    """Clusters doubled until the medoids cover half of the average feature."""
    points = materialise(_conversation_points(spark, sf_dir), "points")
    log = logs.conversations_log(spark, sf_dir)
    toks = materialise(features.tokens(log), "tokens")

    def covers(ids: list[int]) -> bool:
        return metrics.coverage(metrics.compare(toks.where(F.col("qid").isin(ids)), toks)).head()["alpha_avg"] >= 0.5

    return spark.createDataFrame([(i,) for i in baselines.k_medoids_doubling(points, covers, most=16, kind="mixed")], "qid long")


@query
def embedding_kmedoids(spark, sf_dir):
    """Entries known by vectors only: k-medoids over embeddings, with how many true clusters each medoid's own holds."""
    p = materialise(logs.embeddings_log(spark, sf_dir), "vectors")
    ids, _ = baselines.k_medoids(p.select("qid", "num"), 10, "numeric")
    assigned = baselines.medoid_assign(p.select("qid", "num"), p.where(F.col("qid").isin(ids)).select("qid", "num"))
    return assigned.join(p.select("qid", "label"), "qid").groupBy("medoid").agg(F.count("*").alias("n"), F.count_distinct("label").alias("labels"))


@query
def plan_token_kmedoids(spark, sf_dir):
    """Star queries clustered by the operators of their plans."""
    from repsum.functions.plantext import plan_tokens

    for t in _TABLES:
        read(spark, sf_dir, t).createOrReplaceTempView(t)
    log = templates.sql_log(spark, templates.STARS, 4)
    toks = materialise(plan_tokens(spark, log), "plans")
    points = baselines.dense_points(log.select("qid", *templates.STATISTICS), templates.STATISTICS, toks)
    ids, cost = baselines.k_medoids(points, 5, "categorical")
    return spark.createDataFrame([(i, round(cost, 6)) for i in ids], "qid long, cost double")


@query
def mixed_to_chosen(spark, sf_dir):
    """Every conversation against eight by seeded hash, by numbers and names together."""
    p = materialise(_conversation_points(spark, sf_dir), "points")
    return _rounded(baselines.distances_to(p, _chosen(p), "mixed"), "dist")


@query
def compare_methods(spark, sf_dir):
    """Scores at the same size of the methods that no log is too long for, over the skewed orders log.

    ``compare_methods_shared`` has the quadratic ones beside them, on a log that all take whole.
    """
    log = logs.skewed_log(logs.orders_log(spark, sf_dir))
    p = prepare(log)
    k = 40
    ids = {
        "greedy": greedy.compress(p.vectors, p.d, k).ids(),
        "greedy_limit": greedy.compress(p.vectors, p.d, k, "limit").ids(),
        "max_cover": greedy.compress(p.vectors, np.ones(len(p.d)), k, "cover").ids(),
        "random": [r["qid"] for r in baselines.random_sample(log.entries, k).collect()],
        "frequent": [r["qid"] for r in baselines.top_frequency(p.vectors, k).collect()],
    }
    return _method_scores(p, ids)


@query
def compare_methods_shared(spark, sf_dir):
    """Scores of every method at the same size, each over the whole of one skewed log of rendered SQL.

    The log has all templates and, whatever the tables' size, few enough entries for the quadratic methods.
    """
    sql = templates.sql_log(spark, templates.REPORTS + templates.STARS, 20)
    log = logs.skewed_log(features.Log(sql.select("qid", *templates.STATISTICS), sql_tokens(sql), templates.STATISTICS))
    p = prepare(log)
    k = 100
    ids = {
        "greedy": greedy.compress(p.vectors, p.d, k).ids(),
        "greedy_limit": greedy.compress(p.vectors, p.d, k, "limit").ids(),
        "max_cover": greedy.compress(p.vectors, np.ones(len(p.d)), k, "cover").ids(),
        "random": [r["qid"] for r in baselines.random_sample(log.entries, k).collect()],
        "frequent": [r["qid"] for r in baselines.top_frequency(p.vectors, k).collect()],
    }
    points = materialise(baselines.dense_points(log.entries, log.numeric, p.tokens), "points")
    for kind in ("numeric", "categorical", "mixed"):
        ids[f"k_medoids_{kind}"] = baselines.k_medoids(points, k, kind, init="random")[0]
        ids[f"hierarchical_{kind}"] = baselines.hierarchical(points, k, "average", kind)
    return _method_scores(p, ids)


def _method_scores(p: Prepared, ids: dict[str, list[int] | DataFrame]) -> DataFrame:
    out = None
    for name, some in ids.items():
        row = metrics.scores(metrics.compare(p.of(some), p.tokens)).select(F.lit(name).alias("method"), *(F.round(c, 6).alias(c) for c in ("alpha_min", "alpha_avg", "rho_l1", "rho_linf")))
        out = row if out is None else out.unionByName(row)
    return out


# use cases


def _sql_prepared(spark, which):
    log = templates.sql_log(spark, which)
    toks = sql_tokens(log)
    return log, prepare(features.Log(log.select("qid", *templates.STATISTICS), toks, templates.STATISTICS))


_TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")


def _workload(spark, sf_dir, log) -> advisor.Workload:
    return advisor.workload(spark, log, {t: read(spark, sf_dir, t) for t in _TABLES})


def _marks(log) -> dict[int, str]:
    """Shape of each entry of a log that fits a driver."""
    return {r["qid"]: r["mark"] for r in advisor.mark_of(log).collect()}


def _advised(kinds, which, spark, sf_dir):
    log, p = _sql_prepared(spark, which)
    full, marks = _workload(spark, sf_dir, log), _marks(log)
    ids = greedy.compress(p.vectors, p.d, sqrt_budget(log)).ids()
    random = [r["qid"] for r in baselines.random_sample(log, len(ids)).collect()]
    budgets = [500, 2_000, 10_000, 50_000, 200_000, 1_000_000]
    rows = advisor.sweep(full, advisor.summarised(full, [marks[i] for i in ids]), kinds, budgets)
    chance = advisor.sweep(full, advisor.summarised(full, [marks[i] for i in random]), kinds, budgets)
    best = advisor.whatif_cost(full, advisor.optimal(full, kinds))
    out = [(r["budget"], r["full"] / r["none"], r["summary"] / r["none"], c["summary"] / c["none"], best / r["none"]) for r, c in zip(rows, chance)]
    return spark.createDataFrame(out, "evaluations long, full_log double, summary double, random double, optimal double")


for _name, _kinds, _which in (
    ("advise_index_reports", {"index"}, templates.REPORTS),
    ("advise_index_stars", {"index"}, templates.STARS),
    ("advise_views_reports", {"view"}, templates.REPORTS),
    ("advise_views_stars", {"view"}, templates.STARS),
    ("advise_both_reports", {"index", "view"}, templates.REPORTS),
    ("advise_both_stars", {"index", "view"}, templates.STARS),
):

    def _run(spark, sf_dir, kinds=_kinds, which=_which):
        return _advised(kinds, which, spark, sf_dir)

    _run.__name__ = _name
    query(_run)


@query
def summary_size_sweep(spark, sf_dir):
    """Design cost by summary size, against random samples of the same size."""
    log, p = _sql_prepared(spark, templates.STARS)
    full, marks = _workload(spark, sf_dir, log), _marks(log)
    ids = greedy.compress(p.vectors, p.d, 39).ids()
    chance = [r["qid"] for r in baselines.random_sample(log, 39).orderBy("pick_no").collect()]
    none, rows = advisor.whatif_cost(full, []), []
    for k in range(3, 40, 3):
        cost = []
        for some in (ids[:k], chance[:k]):
            w = advisor.summarised(full, [marks[i] for i in some])
            cost.append(advisor.whatif_cost(full, advisor.advise(w, {"index", "view"}, 1_000_000)[0]) / none)
        rows.append((k, *cost, len({marks[i] for i in ids[:k]}), len({marks[i] for i in chance[:k]})))
    return spark.createDataFrame(rows, "k int, summary double, random double, templates_summary int, templates_random int")


@query
def ablation_slowdown(spark, sf_dir):
    """Designs for three tasks from summaries on some features, against the designs from all of them."""
    log, p = _sql_prepared(spark, templates.STARS)
    full, marks = _workload(spark, sf_dir, log), _marks(log)
    categorical = ["function_call", "table_reference", "group_by", "order_by"]
    numeric = ["exec_ms", "rows_out", "n_joins"]
    sets = {"all": []} | {f: [f] for f in (*numeric, *categorical)}
    sets |= {"n_joins + rows_out": ["n_joins", "rows_out"], "exec_ms + n_joins": ["exec_ms", "n_joins"], "exec_ms + rows_out": ["exec_ms", "rows_out"], "all numeric": templates.STATISTICS, "all categorical": categorical}
    tasks = {"index": {"index"}, "views": {"view"}, "index and views": {"index", "view"}}
    cost, hit = {}, {}
    for name, some in sets.items():
        toks = p.tokens.where(F.col("feature").isin(some)) if some else p.tokens
        dom = features.domain(toks)
        got = greedy.compress(materialise(features.pack(toks, dom), "ablated"), greedy.target_array(dom), 13).ids()
        w, hit[name] = advisor.summarised(full, [marks[i] for i in got]), len({marks[i] for i in got})
        for task, kinds in tasks.items():
            cost[name, task] = advisor.whatif_cost(full, advisor.advise(w, kinds, 1_000_000)[0])
    out = [(name, task, c / cost["all", task], hit[name]) for (name, task), c in cost.items()]
    return spark.createDataFrame(out, "features string, task string, slowdown double, templates_hit int")


@query
def templates_hit(spark, sf_dir):
    """Different texts of the star log that a summary of 13 entries by table references alone meets, and one by all features."""
    log, p = _sql_prepared(spark, templates.STARS)
    marks = _marks(log)
    out = []
    for name, toks in (("table_reference", p.tokens.where("feature = 'table_reference'")), ("all", p.tokens)):
        dom = features.domain(toks)
        got = greedy.compress(materialise(features.pack(toks, dom), "vectors"), greedy.target_array(dom), 13).ids()
        out.append((name, len({marks[i] for i in got}), len(set(marks.values()))))
    return spark.createDataFrame(out, "features string, hit int, texts int")


@query
def index_candidates(spark, sf_dir):
    log = templates.sql_log(spark, templates.STARS)
    found = advisor.design_table(spark, advisor.candidates(_workload(spark, sf_dir, log), {"index", "view"}))
    return found.select("kind", "tbl", F.array_join("cols", ",").alias("cols"), "rows")


@query
def whatif_cost(spark, sf_dir):
    """What the whole star log reads under each candidate structure alone."""
    log = templates.sql_log(spark, templates.STARS)
    return advisor.whatif_table(spark, log, _workload(spark, sf_dir, log))


@query
def advise_greedy_4(spark, sf_dir):
    """Four structures by greedy choice with all the patience needed, and what the star log reads after each."""
    log = templates.sql_log(spark, templates.STARS)
    w = _workload(spark, sf_dir, log)
    design, _ = advisor.advise(w, {"index", "view"}, 1 << 60, 4)
    rows = [(n, s.kind, ",".join(s.tables), ",".join(s.cols), advisor.whatif_cost(w, design[:n])) for n, s in enumerate(design, 1)]
    return spark.createDataFrame(rows, "pick_no int, kind string, tbl string, cols string, cost long")


# relational surface of the methods


@query
def sql_surface(spark, sf_dir):
    """Views of a log and the registered functions in plain SQL: tokens of each feature by price bucket."""
    register(spark)
    log = logs.orders_log(spark, sf_dir)
    views(log, "orders_log")
    return spark.sql(
        """WITH e AS (SELECT qid, token_bucket(n1, (SELECT min(n1) FROM orders_log_entries), (SELECT max(n1) FROM orders_log_entries), 10) AS bucket FROM orders_log_entries)
        SELECT bucket, feature, sum(mult) AS n FROM e JOIN orders_log_tokens USING (qid) GROUP BY bucket, feature"""
    )


@query
def bucket_range_join(spark, sf_dir):
    b = spark.range(10).select(F.col("id").alias("bucket"), (F.col("id") * 50000).alias("lo"), ((F.col("id") + 1) * 50000).alias("hi"))
    o = read(spark, sf_dir, "orders").select("o_totalprice")
    return o.join(F.broadcast(b), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("bucket").agg(F.count("*").alias("n"))


@query
def asof_prev_event(spark, sf_dir):
    """Latest event of a customer at or before a shifted order date: union, then last over the merged order."""
    e = read(spark, sf_dir, "events").select(F.col("user_id").alias("k"), F.col("ts").alias("t"), F.col("event_id"), F.lit(None).cast("long").alias("o_orderkey"), F.lit(0).alias("side"))
    o = read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k"), F.expr("o_orderdate + interval 25 years").alias("t"), F.lit(None).cast("long").alias("event_id"), "o_orderkey", F.lit(1).alias("side"))
    w = Window.partitionBy("k").orderBy("t", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(o).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w)).where("side = 1 and event_id is not null").select("o_orderkey", "event_id")


@query
def interval_concurrency(spark, sf_dir):
    """Events of a user within an hour of each event; hours are part of the key, so a busy user is spread over hours."""
    e = read(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.date_trunc("hour", "ts").alias("h"))
    hours = F.explode(F.array(F.expr("h - interval 1 hour"), F.col("h"), F.expr("h + interval 1 hour"))).alias("g")
    b = e.select(F.col("user_id").alias("u"), F.col("ts").alias("t"), hours)
    near = e.join(b, (F.col("user_id") == F.col("u")) & (F.col("h") == F.col("g")) & F.col("t").between(F.expr("ts - interval 1 hour"), F.expr("ts + interval 1 hour")))
    return near.groupBy("event_id").agg((F.count("*") - 1).alias("near"))


@query
def view_sizes_cube(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("gid"), F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"))


@query
def scores_rollup(spark, sf_dir):
    log = logs.events_log(spark, sf_dir)
    toks = features.tokens(log).join(log.entries.select("qid", F.to_date("ts").alias("day")), "qid")
    return toks.rollup("feature", "day").agg(F.sum("mult").alias("n"))


@query
def scores_gsets(spark, sf_dir):
    read(spark, sf_dir, "events").createOrReplaceTempView("events_gs")
    return spark.sql("select event_type, user_id, count(*) as n from events_gs group by grouping sets ((event_type), (user_id), ())")


@query
def gamma_grid(spark, sf_dir):
    both = _sampled(spark, sf_dir)[2]
    each = F.explode(F.array(*(F.struct(F.lit(n).alias("col"), F.lit(g).alias("gamma")) for n, g in (("g1", 1.0), ("g2", 0.001), ("g3", 1e-10))))).alias("x")
    long = both.select("feature", "d", "ms", each).select("feature", "x.col", F.when(F.col("ms") > 0, F.col("d") * (F.log(F.col("ms") + F.col("x.gamma")) - F.log("x.gamma"))).otherwise(0.0).alias("g"))
    return _rounded(long.groupBy("feature").pivot("col", ["g1", "g2", "g3"]).agg(F.sum("g")), "g1", "g2", "g3")


@query
def profile_numeric(spark, sf_dir):
    log = logs.orders_log(spark, sf_dir)
    row = log.entries.agg(*(x for f in log.numeric for x in (F.avg(f).alias(f"m_{f}"), F.percentile(f, F.lit(0.5)).alias(f"d_{f}"), F.percentile(f, F.lit(0.9)).alias(f"p_{f}"))))
    each = F.array(*(F.struct(F.lit(f).alias("feature"), F.round(f"m_{f}", 3).alias("mean"), F.round(f"d_{f}", 3).alias("median"), F.round(f"p_{f}", 3).alias("p90")) for f in log.numeric))
    return row.select(F.explode(each).alias("x")).select("x.*")


@query
def moving_freq(spark, sf_dir):
    per = read(spark, sf_dir, "events").groupBy("event_type", F.to_date("ts").alias("day")).agg(F.count("*").alias("n"))
    w = Window.partitionBy("event_type").orderBy(F.datediff("day", F.lit("2024-01-01").cast("date"))).rangeBetween(-6, 0)
    return per.select("event_type", "day", F.sum("n").over(w).alias("n7"))


@query
def event_bigrams(spark, sf_dir):
    return logs.events_log(spark, sf_dir).bags.where("feature = 'bigram'").groupBy("token").agg(F.sum("mult").alias("n"))


@query
def json_props(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


@query
def hour_tokens(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy(F.hour("ts").alias("hour")).agg(F.count("*").alias("n"))


@query
def tumbling_counts(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("day"), "event_type", "n")


@query
def sliding_counts(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy(F.window("ts", "7 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


@query
def session_counts(spark, sf_dir):
    e = read(spark, sf_dir, "events").groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("k"))
    return e.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("k").alias("n"))


@query
def pred_mix(spark, sf_dir):
    o = read(spark, sf_dir, "orders")
    kept = o.where(F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 300000) & F.col("o_orderpriority").like("%-%") & F.col("o_orderdate").isNotNull())
    return kept.groupBy("o_orderpriority").agg(F.count("*").alias("n"))


def _edge_batches(spark, sf_dir):
    log, b = _batches(spark, sf_dir)
    tagged = features.tokens(log).join(b, "qid")
    return (tagged.where(part).select("feature", "token") for part in (F.col("batch") == 1, F.col("batch") > 1))


@query
def set_intersect(spark, sf_dir):
    a, b = _edge_batches(spark, sf_dir)
    return a.intersect(b)


@query
def set_except(spark, sf_dir):
    a, b = _edge_batches(spark, sf_dir)
    return a.subtract(b)


@query
def set_intersect_all(spark, sf_dir):
    """Tokens as often as both the first batch and all later ones have them."""
    a, b = _edge_batches(spark, sf_dir)
    return a.intersectAll(b).groupBy("feature", "token").agg(F.count("*").alias("n"))


@query
def set_except_all(spark, sf_dir):
    a, b = _edge_batches(spark, sf_dir)
    return a.exceptAll(b).groupBy("feature", "token").agg(F.count("*").alias("n"))


@query
def boost_rounds(spark, sf_dir):
    """Representativity as the weights of under-represented tokens are raised."""
    _, rows = tuning.boost_weights(_orders(spark, sf_dir), 50, 4)
    return spark.createDataFrame([(r["round"], r["rho_l1"], r["covered"]) for r in rows], "round int, rho_l1 double, covered int")


@query
def testgen_boosted(spark, sf_dir):
    """A test workload that favours one feature."""
    log = logs.orders_log(spark, sf_dir)
    return _eight(prepare(log, target=tuning.boosted_target(features.tokens(log), "ob", 20.0)))


@query
def plan_operator_tokens(spark, sf_dir):
    from repsum.functions.plantext import plan_tokens

    for t in _TABLES:
        read(spark, sf_dir, t).createOrReplaceTempView(t)
    return plan_tokens(spark, templates.order_log(spark, sf_dir, templates.STARS))


@query
def anonymised_export(spark, sf_dir):
    """Summary texts of the report log with their literals replaced."""
    from repsum.functions.sqltext import anonymise

    log, p = _sql_prepared(spark, templates.REPORTS)
    ids = greedy.compress(p.vectors, p.d, sqrt_budget(log)).ids()
    return log.where(F.col("qid").isin(ids)).select("qid", anonymise(F.col("sql"), "salt").alias("sql"))


__all__ = ["QUERIES", "cents"]
