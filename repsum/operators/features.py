"""From log entries to tokens, domains and packed vectors.

A token is a (feature, token) pair: equal strings of two features never merge. ``mult`` is how
often an entry has it. Null values yield no token.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window, functions as F

from repsum.functions.numeric import bounds, bucket
from repsum.operators.encode import Rows
from repsum.plans.ranks import positions
from repsum.plans.scratch import materialise

BUCKETS = 1000
#: Tokens of one feature beyond which its domain is considered too large to be useful.
LARGE_DOMAIN = 100_000


@dataclass
class Log:
    """Entries with their numeric columns, and the bags of their categorical features."""

    entries: DataFrame  # qid, ts?, numeric columns
    bags: DataFrame  # qid, feature, token, mult
    numeric: list[str] = field(default_factory=list)
    rows: Rows | None = None  # what entries and bags are made of, if the log can give it


def numeric_tokens(entries: DataFrame, features: list[str], buckets: int = BUCKETS, pinned: dict[str, tuple[int, int]] | None = None) -> DataFrame:
    """One token per entry and numeric feature. The bounds are one row, whatever the log."""
    if pinned is None:
        edge = F.broadcast(bounds(entries, features))
        wide = entries.crossJoin(edge)
        low, high = (lambda f: F.col(f"lo_{f}")), (lambda f: F.col(f"hi_{f}"))
    else:
        wide = entries
        low, high = (lambda f: F.lit(pinned[f][0])), (lambda f: F.lit(pinned[f][1]))
    each = F.array(*(F.struct(F.lit(f).alias("feature"), bucket(F.col(f), low(f), high(f), buckets).cast("string").alias("token")) for f in features))
    return wide.select("qid", F.explode(each).alias("t")).select("qid", "t.feature", "t.token", F.lit(1).cast("long").alias("mult")).where(F.col("token").isNotNull())


def tokens(log: Log, buckets: int = BUCKETS, pinned: dict[str, tuple[int, int]] | None = None) -> DataFrame:
    """(qid, feature, token, mult) of a whole log."""
    if not log.numeric:
        return log.bags
    return log.bags.unionByName(numeric_tokens(log.entries, log.numeric, buckets, pinned))


def count_bag(rows: DataFrame, qid: str, **columns) -> DataFrame:
    """Multiset of categorical values: explode the given columns of each row, count per entry."""
    each = F.array(*(F.struct(F.lit(f).alias("feature"), c.cast("string").alias("token")) for f, c in columns.items()))
    long = rows.select(F.col(qid).alias("qid"), F.explode(each).alias("t")).select("qid", "t.feature", "t.token").where(F.col("token").isNotNull())
    return long.groupBy("qid", "feature", "token").agg(F.count("*").alias("mult"))


def frequencies(toks: DataFrame) -> DataFrame:
    """(feature, token, freq): combined on the map side, so hot tokens do not skew."""
    return toks.groupBy("feature", "token").agg(F.sum("mult").alias("freq"))


def distribution(toks: DataFrame) -> DataFrame:
    """(feature, token, freq, p): shares of all tokens."""
    freq = frequencies(toks)
    total = freq.agg(F.sum("freq").alias("z"))  # one row
    return freq.crossJoin(F.broadcast(total)).select("feature", "token", "freq", (F.col("freq") / F.col("z")).alias("p"))


#: Domain sizes whose state may be shipped to every task: two doubles per token.
MAX_DOMAIN = 20_000_000
#: Distinct tokens that one task numbers, and that are broadcast to the tokens of a log.
SMALL_DOMAIN = 1_000_000


def domain(toks: DataFrame) -> DataFrame:
    """(tid, feature, token, freq) with dense ids in (feature, token) order; its size is checked before anything else.

    Up to a million distinct tokens are numbered in one task, more by ranges. Domains beyond a
    broadcast have no dense ids: see greedy.compress_by_join().
    """
    return numbered(frequencies(toks))


def numbered(freq: DataFrame) -> DataFrame:
    """domain() of (feature, token, freq)."""
    freq = materialise(freq, "frequencies")
    size = freq.count()
    if size > MAX_DOMAIN:
        raise ValueError(f"a domain of {size} tokens is too large to ship; use greedy.compress_by_join()")
    if size > SMALL_DOMAIN:
        ranked = positions(freq.withColumn("all", F.lit(0)), ["all"], ["feature", "token"], "tid")
        return ranked.select(F.col("tid").cast("int").alias("tid"), "feature", "token", "freq")
    return freq.select((F.row_number().over(Window.orderBy("feature", "token")) - 1).cast("int").alias("tid"), "feature", "token", "freq")


def with_domain(toks: DataFrame, dom: DataFrame, salts: int = 16) -> DataFrame:
    """Tokens beside the domain's columns. A small domain is broadcast; a larger one is repeated ``salts`` times,
    so that a token that a third of the log has is spread over as many tasks."""
    if dom.limit(SMALL_DOMAIN + 1).count() <= SMALL_DOMAIN:
        return toks.join(F.broadcast(dom), ["feature", "token"])
    salted = dom.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return toks.withColumn("salt", F.pmod(F.xxhash64("qid"), F.lit(salts)).cast("int")).join(salted, ["feature", "token", "salt"]).drop("salt")


def query_sizes(toks: DataFrame) -> DataFrame:
    return toks.groupBy("qid").agg(F.sum("mult").alias("size"))


def pack(toks: DataFrame, dom: DataFrame, costs: DataFrame | None = None) -> DataFrame:
    """(qid, cost, tids, mults): one row per entry, sorted by tid; cost 1 unless given."""
    ids = dom.select("tid", "feature", "token")
    wide = with_domain(toks, ids).groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("tid", "mult"))).alias("v"))
    packed = wide.select("qid", F.col("v.tid").alias("tids"), F.transform("v.mult", lambda m: m.cast("int")).alias("mults"))
    if costs is None:
        return packed.select("qid", F.lit(1.0).alias("cost"), "tids", "mults")
    return packed.join(costs.select("qid", F.col("cost").cast("double").alias("cost")), "qid").select("qid", "cost", "tids", "mults")


def cross_feature(toks: DataFrame, a: str, b: str) -> DataFrame:
    """Tokens of the higher-order feature a x b: pairs within an entry, multiplicities multiplied."""
    left = toks.where(F.col("feature") == a).select("qid", F.col("token").alias("ta"), F.col("mult").alias("ma"))
    right = toks.where(F.col("feature") == b).select("qid", F.col("token").alias("tb"), F.col("mult").alias("mb"))
    pairs = left.join(right, "qid").select("qid", F.lit(f"{a}×{b}").alias("feature"), F.concat_ws("×", "ta", "tb").alias("token"), (F.col("ma") * F.col("mb")).alias("mult"))
    return pairs.groupBy("qid", "feature", "token").agg(F.sum("mult").alias("mult"))


def domain_advice(dom: DataFrame, large: int = LARGE_DOMAIN) -> DataFrame:
    """(feature, tokens, occurrences, advice): which features are too large to keep as they are."""
    per = dom.groupBy("feature").agg(F.count("*").alias("tokens"), F.sum("freq").alias("occurrences"))
    return per.withColumn("advice", F.when(F.col("tokens") > large, "drop or weigh down").when(F.col("tokens") == 1, "constant").otherwise("keep"))


def inverse_domain_weights(dom: DataFrame) -> DataFrame:
    """(feature, w) proportional to one over the feature's domain size; the weights sum to 1."""
    per = dom.groupBy("feature").agg((1 / F.count("*")).alias("x"))
    return per.select("feature", (F.col("x") / F.sum("x").over(Window.partitionBy())).alias("w"))


def numeric_correlation(entries: DataFrame, features: list[str]) -> DataFrame:
    """(a, b, r): Pearson correlation of each pair of numeric features, in one pass."""
    pairs = [(a, b) for i, a in enumerate(features) for b in features[i + 1 :]]
    row = entries.agg(*(F.corr(F.col(a).cast("double"), F.col(b).cast("double")).alias(f"{a}~{b}") for a, b in pairs))
    each = F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(f"{a}~{b}").alias("r")) for a, b in pairs))
    return row.select(F.explode(each).alias("x")).select("x.a", "x.b", "x.r")


def cramers_v(rows: DataFrame, a: str, b: str) -> DataFrame:
    """(a, b, v): association of two single-valued categorical columns."""
    joint = rows.where(F.col(a).isNotNull() & F.col(b).isNotNull()).groupBy(a, b).agg(F.count("*").alias("n"))
    with_margins = joint.withColumn("na", F.sum("n").over(Window.partitionBy(a))).withColumn("nb", F.sum("n").over(Window.partitionBy(b))).withColumn("z", F.sum("n").over(Window.partitionBy()))
    # chi2 / z = sum n^2 / (na nb) - 1
    got = with_margins.agg((F.sum(F.col("n") * F.col("n") / (F.col("na") * F.col("nb"))) - 1).alias("phi"), F.count_distinct(a).alias("ka"), F.count_distinct(b).alias("kb"))
    return got.select(F.lit(a).alias("a"), F.lit(b).alias("b"), F.sqrt(F.greatest(F.col("phi"), F.lit(0.0)) / (F.least("ka", "kb") - 1)).alias("v"))
