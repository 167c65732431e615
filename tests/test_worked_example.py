"""The three-query worked example, exactly."""

from fractions import Fraction as Q
from math import log

import pytest
from pyspark.sql import functions as F

from repsum.operators import features, greedy, metrics
from repsum.sources.logs import toy_tokens

#: subset: size, rho_l1, rho_linf, alpha_min, alpha_avg, G at gamma 1, 0.1 and 1e-6
EXPECTED = {
    (1,): (11, Q(71, 176), Q(155, 176), Q(0), Q(2, 5), 0.306933, 1.014559, 5.655873),
    (2,): (9, Q(3, 8), Q(265, 288), Q(0), Q(3, 10), 0.259930, 0.899211, 5.180817),
    (3,): (12, Q(11, 24), Q(15, 16), Q(0), Q(2, 5), 0.324913, 1.124013, 6.476021),
    (1, 2): (20, Q(27, 40), Q(77, 80), Q(0), Q(2, 3), 0.539893, 1.749588, 9.606468),
    # the published 0.779 for the first representativity of this pair is a slip
    (1, 3): (23, Q(139, 184), Q(31, 32), Q(2, 3), Q(23, 30), 0.604875, 1.974391, 10.901673),
    (2, 3): (21, Q(11, 16), Q(15, 16), Q(0), Q(19, 30), 0.539893, 1.749588, 9.606468),
    (1, 2, 3): (32, Q(1), Q(1), Q(1), Q(1), 0.808813, 2.575857, 14.005150),
}


@pytest.fixture(scope="module")
def toy(spark):
    return toy_tokens(spark).cache()


def test_sizes_and_buckets(toy):
    assert {r.qid: r["size"] for r in features.query_sizes(toy).collect()} == {1: 11, 2: 9, 3: 12}
    got = {q: [r.token for r in toy.where(F.col("feature").like("n%") & (F.col("qid") == q)).orderBy("feature").collect()] for q in (1, 2, 3)}
    # the third bucket of the second query is 3: the published table prints 6
    assert got == {1: list("060000"), 2: ["10", "0", "3", "10", "5", "5"], 3: ["6", "10", "10", "4", "10", "10"]}


def test_tokens_of_two_features_do_not_merge(toy):
    assert features.frequencies(toy).where("token = 'T1.a'").count() == 2


@pytest.mark.parametrize("subset", list(EXPECTED))
def test_scores(toy, subset):
    size, l1, linf, least, mean, *gs = EXPECTED[subset]
    own = toy.where(F.col("qid").isin(list(subset)))
    assert own.agg(F.sum("mult")).head()[0] == size
    both = metrics.compare(own, toy).cache()
    row = metrics.scores(both).head()
    assert row.rho_l1 == pytest.approx(float(l1), abs=1e-12) and row.rho_linf == pytest.approx(float(linf), abs=1e-12)
    assert row.alpha_min == pytest.approx(float(least)) and row.alpha_avg == pytest.approx(float(mean))
    for gamma, g in zip((1.0, 0.1, 1e-6), gs):
        assert metrics.objective(both, gamma).head().g == pytest.approx(g, abs=1e-6)


def test_empty_summary_scores_nothing(toy):
    both = metrics.compare(toy.where("false"), toy)
    row = metrics.scores(both).head()
    assert (row.alpha_min, row.alpha_avg, row.rho_l1, row.rho_linf) == (0, 0, 0, 0)
    assert metrics.objective(both, 1e-6).head().g == 0


def test_representativity_is_not_submodular(toy):
    score = lambda s: metrics.representativity(metrics.compare(toy.where(F.col("qid").isin(s)), toy)).head().rho_l1
    assert score([2, 3]) - score([3]) == pytest.approx(0.2292, abs=1e-4)
    assert score([1, 2, 3]) - score([1, 3]) == pytest.approx(0.2446, abs=1e-4)


def test_representativity_is_not_monotone(spark):
    toks = spark.createDataFrame([(1, "f", "x", 1), (2, "f", "x", 1), (3, "f", "y", 1), (4, "f", "y", 1)], "qid long, feature string, token string, mult long")
    score = lambda s: metrics.representativity(metrics.compare(toks.where(F.col("qid").isin(s)), toks)).head().rho_l1
    assert score([1, 3]) == 1 and score([1, 2, 3]) == pytest.approx(5 / 6)


def test_divergence_identity_and_pinsker(toy):
    """With everything covered, G + ln gamma tends to -KL - H + ln of the summary's size."""
    own = toy.where("qid < 3").unionByName(toy)  # a multiset that covers all tokens
    both = metrics.compare(own, toy).cache()
    d = metrics.divergence(both).head()
    g = metrics.objective(both, 1e-12).head().g
    size = own.agg(F.sum("mult")).head()[0]
    assert g + log(1e-12) == pytest.approx(-d.kl - d.entropy + log(size), abs=1e-6)
    assert d.kl >= 0 and 1 - metrics.representativity(both).head().rho_l1 <= (d.kl / 2) ** 0.5


@pytest.mark.parametrize("gamma", [1.0, 0.1, 1e-6])
def test_greedy_order(toy, gamma):
    dom = features.domain(toy)
    got = greedy.compress(features.pack(toy, dom), greedy.target_array(dom), 3, gamma)
    assert got.ids() == [3, 1, 2]
