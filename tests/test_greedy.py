import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from repsum.operators import greedy, incremental, partitioned
from repsum.operators.greedy import Pick


def make(rows):
    """rows: (qid, cost, {tid: mult})"""
    return [Pick(q, 0.0, float(c), np.array(sorted(v), np.int64), np.array([v[t] for t in sorted(v)], np.int64)) for q, c, v in rows]


def frame(spark, picks):
    return spark.createDataFrame([(p.qid, p.cost, p.tids.tolist(), p.mults.tolist()) for p in picks], "qid long, cost double, tids array<int>, mults array<int>")


def random_log(seed, n, tokens=12, costs=False):
    rng = random.Random(seed)
    rows = [(q, rng.choice([1, 2, 3, 5]) if costs else 1, {t: rng.randint(1, 3) for t in rng.sample(range(tokens), rng.randint(1, 5))}) for q in range(n)]
    d = np.zeros(tokens)
    for _, _, v in rows:
        for t, m in v.items():
            d[t] += m
    return make(rows), d / d.sum()


def reference(picks, d, budget, gamma, unit=True):
    """Greedy by its definition."""
    m, left, out, rest = np.zeros(len(d)), budget, [], list(picks)
    while rest:
        fit = [p for p in rest if p.cost <= left]
        if not fit:
            break

        def key(p):
            gain = np.round(greedy.gain_of(d, m, p.tids, p.mults, np.zeros(1, np.int64), gamma)[0], greedy.DIGITS)
            return (tuple(gain / p.cost) if gamma == "limit" else (np.round(gain / p.cost, greedy.DIGITS),), -p.qid)

        best = max(fit, key=key)
        m[best.tids] += best.mults
        left -= best.cost
        out.append(best.qid)
        rest.remove(best)
    return out


@pytest.mark.parametrize("gamma", [1.0, 1e-25, "limit"])
@pytest.mark.parametrize("costs", [False, True])
def test_strategies_pick_alike(spark, gamma, costs):
    picks, d = random_log(7, 60, costs=costs)
    df = frame(spark, picks).repartition(3).cache()
    budget = 15 if costs else 9
    want = reference(picks, d, budget, gamma)
    for strategy, pool in (("eager", 1), ("lazy", 1), ("fenced", 1), ("fenced", 7), ("fenced", 500)):
        got = greedy.compress(df, d, budget, gamma, strategy, pool, unit=not costs, safeguard=False)
        assert got.ids() == want, (strategy, pool)


@pytest.mark.parametrize("gamma", [1.0, 1e-25, "limit"])
def test_few_rows_of_each_task_suffice(spark, gamma, monkeypatch):
    """Tasks hand over their share and a marker of what they leave out, here one row of twelve tasks with the best entries in one of them."""
    monkeypatch.setattr(greedy, "LEAST_OF_TASK", 1)
    monkeypatch.setattr(greedy, "CHUNK", 3)
    picks, d = random_log(11, 240)
    order = reference(picks, d, 240, gamma)
    place = {q: n for n, q in enumerate(order)}
    df = frame(spark, picks).repartitionByRange(12, F.element_at(F.create_map(*(F.lit(x) for kv in place.items() for x in kv)), F.col("qid"))).cache()
    for pool in (1, 5, 40):
        assert greedy.compress(df, d, 30, gamma, "fenced", pool).ids() == order[:30], pool


@pytest.mark.parametrize("seed", range(6))
def test_local_lazy_equals_definition(seed):
    for gamma in (1.0, 1e-6, 1e-25, "limit"):
        picks, d = random_log(seed, 40)
        assert partitioned._local(picks, d, 8, True, gamma).ids() == reference(picks, d, 8, gamma)


def test_first_pick_is_the_best_one(spark):
    picks = make([(0, 1, {0: 1}), (1, 1, {1: 5, 2: 5}), (2, 1, {0: 2})])
    assert greedy.compress(frame(spark, picks), np.array([0.1, 0.5, 0.4]), 1).ids() == [1]


def test_best_single_entry_wins(spark):
    picks = make([(0, 1, {0: 1}), (1, 10, {1: 1, 2: 1})])
    d = np.array([0.2, 0.4, 0.4])
    got = greedy.compress(frame(spark, picks), d, 10, 1.0, unit=False)
    assert got.ids() == [1] and got.winner == "single" and got.picks[0].cost == 10
    assert greedy.compress(frame(spark, picks), d, 10, 1.0, unit=False, safeguard=False).ids() == [0]


def test_edges(spark):
    picks = make([(0, 0, {0: 1}), (1, 4, {1: 1}), (2, 3, {0: 1}), (3, 1, {})])
    d = np.array([0.5, 0.5])
    df = frame(spark, picks)
    assert greedy.compress(df, d, 0, 1e-6, unit=False, safeguard=False).ids() == [0]
    assert sorted(greedy.compress(df, d, 100, 1e-6, unit=False, safeguard=False).ids()) == [0, 1, 2, 3]
    assert greedy.compress(df.where("false"), d, 3).ids() == []
    ones = make([(p.qid, 1, dict(zip(p.tids.tolist(), p.mults.tolist()))) for p in picks])
    assert greedy.compress(frame(spark, ones), d, 2, exclude=[0, 1]).ids()[0] == 2
    forced = greedy.compress(frame(spark, ones), d, 2, include=[ones[3]])
    assert forced.ids()[0] == 3 and len(forced.ids()) == 2


def test_duplicates_may_each_be_chosen(spark):
    picks = make([(q, 1, {0: 1, 1: 1}) for q in (5, 3, 9)])
    df = frame(spark, picks)
    assert greedy.compress(df, np.array([0.5, 0.5]), 2, 1.0).ids() == [3, 5]
    assert [r.qid for r in greedy.collapse(df, 2).orderBy("qid").collect()] == [3, 5]


@pytest.mark.parametrize("seed", range(5))
def test_guarantee_and_properties(seed):
    picks, d = random_log(seed, 10, 8)
    gamma = 0.01
    for k in (2, 4):
        best = max(greedy.value(d, list(s), gamma) for s in itertools.combinations(picks, k))
        got = greedy.value(d, partitioned._local(picks, d, k, True, gamma).picks, gamma)
        assert got >= (1 - 1 / np.e) * best - 1e-9
    rng = random.Random(seed)
    small = rng.sample(picks, 3)
    large = small + [p for p in picks if p not in small][:3]
    extra = next(p for p in picks if p not in large)
    g = lambda s: greedy.value(d, s, gamma)
    assert 0 <= g(small) <= g(large)
    assert g([*small, extra]) - g(small) >= g([*large, extra]) - g(large) - 1e-12


def test_limit_prefers_the_larger_token_set():
    d = np.array([0.9, 0.05, 0.05])
    many, heavy = make([(0, 1, {0: 1, 1: 1})]), make([(1, 1, {0: 1000})])
    assert greedy.value(d, many, "limit") > greedy.value(d, heavy, "limit")
    assert greedy.value(d, many, 1.0) < greedy.value(d, heavy, 1.0)


def test_parts(spark):
    picks, d = random_log(3, 80)
    df = frame(spark, picks).cache()
    whole = greedy.compress(df, d, 8, 1e-6)
    one = partitioned.compress_partitioned(df, d, 8, 1, 1e-6)
    assert one.ids() == whole.ids()
    for parts, levels in ((4, 1), ("budget", 1), (9, 2)):
        got = partitioned.compress_partitioned(df, d, 8, parts, 1e-6, levels=levels, fan=3)
        assert len(got.picks) == 8 and greedy.value(d, got.picks, 1e-6) >= 0.9 * greedy.value(d, whole.picks, 1e-6)


def test_incremental(spark):
    picks, d = random_log(4, 70)
    df = frame(spark, picks).cache()
    batch = spark.createDataFrame([(p.qid, p.qid // 10 + 1) for p in picks], "qid long, batch int")
    steps = incremental.run_incremental(df, batch, [d] * 7, lambda n: 5, 1e-6)
    assert [s["looked_at"] for s in steps] == list(range(10, 80, 10)) and steps[-1]["scratch_looked_at"] == 280
    for n, s in enumerate(steps, 1):  # each run from scratch is greedy over the log up to its batch
        assert s["scratch"].ids() == greedy.compress(df.where(F.col("qid") < 10 * n), d, 5, 1e-6).ids()
    whole = greedy.compress(df, d, 5, 1e-6)
    assert greedy.value(d, steps[-1]["result"].picks, 1e-6) >= 0.9 * greedy.value(d, whole.picks, 1e-6)


def test_merging_unequal_logs_loses_representativity(spark):
    """Two perfect one-token summaries of logs with mass 99 and 1 merge to 0.51."""
    from repsum.operators import metrics

    schema = "qid long, feature string, token string, mult long"
    w = spark.createDataFrame([(1, "f", "a", 99), (2, "f", "b", 1)], schema)
    s = spark.createDataFrame([(1, "f", "a", 1), (2, "f", "b", 1)], schema)
    assert metrics.representativity(metrics.compare(s, w)).head().rho_linf == pytest.approx(0.51)
    one = metrics.compare(s.where("qid = 1"), w.where("qid = 1"))
    two = metrics.compare(s.where("qid = 2"), w.where("qid = 2"))
    row = incremental.merge_bounds(one, two, metrics.compare(s, w), (1, 1, 99, 1)).head()
    assert row.rho_bound == 1 and not row.proportional and row.alpha_ab >= row.alpha_bound


def test_trace_and_prefix():
    picks, d = random_log(5, 30)
    got = partitioned._local(picks, d, 10, True, 1e-6)
    rows = greedy.trace(got, d, np.array(["f"] * 6 + ["g"] * 6), 1e-6)
    assert [r["pick_no"] for r in rows] == list(range(1, 11))
    assert all(b["g"] >= a["g"] and b["alpha_avg"] >= a["alpha_avg"] for a, b in zip(rows, rows[1:]))
    n = greedy.best_prefix(rows)
    assert rows[n - 1]["score"] == max(r["score"] for r in rows)
    assert greedy.size_for(rows, 2.0) is None and greedy.size_for(rows, 0.0) == 1


def test_strategies_refuse_what_they_cannot_hold(spark, monkeypatch):
    picks, d = random_log(5, 40)
    df = frame(spark, picks)
    monkeypatch.setattr(greedy, "MAX_POOL", 8)
    with pytest.raises(ValueError):
        greedy.compress(df, d, 5, 1e-6, strategy="lazy")
    assert greedy.compress(df, d, 12, 1e-6, pool=64).ids() == greedy.compress(df, d, 12, 1e-6, strategy="eager").ids()


def test_domain_is_checked_and_numbered_by_ranges(spark, monkeypatch):
    from repsum.operators import features

    rows = [(q, f"f{q % 3}", f"t{q * 7 % 50}", 1) for q in range(200)]
    toks = spark.createDataFrame(rows, "qid long, feature string, token string, mult long")
    small = [tuple(r) for r in features.domain(toks).orderBy("tid").collect()]
    packed = sorted((r.qid, *r.tids) for r in features.pack(toks, features.domain(toks)).collect())
    monkeypatch.setattr(features, "SMALL_DOMAIN", 10)
    dom = features.domain(toks)
    assert [tuple(r) for r in dom.orderBy("tid").collect()] == small
    assert sorted((r.qid, *r.tids) for r in features.pack(toks, dom).collect()) == packed  # salted join
    monkeypatch.setattr(features, "MAX_DOMAIN", 20)
    with pytest.raises(ValueError):
        features.domain(toks)


def test_greedy_by_join_equals_greedy(spark):
    from repsum.operators import features

    rng = np.random.default_rng(6)
    rows = sorted({(int(q), f"f{q % 2}", f"t{t}") for q, t in zip(rng.integers(0, 60, 400), rng.integers(0, 40, 400))})
    toks = spark.createDataFrame([(*r, int(rng.integers(1, 4))) for r in rows], "qid long, feature string, token string, mult long").cache()
    dom = features.domain(toks)
    vectors = features.pack(toks, dom)
    want = greedy.compress(vectors, greedy.target_array(dom), 15, 0.01, strategy="eager")
    target = features.distribution(toks).select("feature", "token", F.col("p").alias("d"))
    for pool in (1, 7, 256):
        got = greedy.compress_by_join(toks, target, 15, 0.01, pool).collect()
        assert [r.qid for r in got] == want.ids()
        assert [r.gain for r in got] == pytest.approx([p.gain for p in want.picks], abs=1e-6)


def test_cover_counts_new_tokens(spark):
    picks, d = random_log(7, 60)
    df, ones = frame(spark, picks), np.ones(len(d))
    got = greedy.compress(df, ones, 6, "cover")
    seen, left = set(), {p.qid: set(p.tids.tolist()) for p in picks}
    for p in got.picks:
        best = max(left, key=lambda q: (len(left[q] - seen), -q))
        assert p.qid == best and p.gain == len(left[best] - seen)
        seen |= left.pop(best)


def test_prefix_targets_and_feature_scores(spark):
    from repsum.operators import features, metrics

    toks = spark.createDataFrame([(1, "a", "x", 2), (2, "a", "y", 1), (2, "b", "z", 1), (3, "b", "w", 4)], "qid long, feature string, token string, mult long")
    dom = features.domain(toks)
    of = spark.createDataFrame([(1, 1), (2, 2), (3, 3)], "qid long, batch int")
    got = incremental.prefix_targets(toks, dom, of, 3, 4)
    assert [t.tolist() for t in got] == [[1.0, 0, 0, 0], [0.5, 0.25, 0, 0.25], [0.25, 0.125, 0.5, 0.125]]
    vectors = features.pack(toks, dom)
    picks = greedy.compress(vectors, got[-1], 2).picks
    want = {r.feature: (r.alpha, r.rho_l1) for r in metrics.scores_by_feature(metrics.compare(toks.where(F.col("qid").isin([p.qid for p in picks])), toks)).collect()}
    rows = greedy.feature_scores(picks, got[-1], np.array([0, 0, 1, 1]), ["a", "b"])
    assert {f: (a, pytest.approx(r)) for f, a, r in rows} == want


def test_merge_refuses_nothing_it_knows():
    rows = [{"score": s, "pick_no": n} for n, s in enumerate((0.2, 0.5, 0.5, 0.4), 1)]
    assert greedy.best_prefix(rows) == 2 and greedy.size_for(rows, 0.45) == 2 and greedy.size_for(rows, 0.9) is None
    assert greedy.best_prefix([]) == 0


def test_pools_are_arrays_and_limit_needs_few_passes(spark):
    """A pool of any size is a few arrays, and a covered log is picked from by bounds: one pass serves many picks."""
    picks, d = random_log(13, 300)
    df = frame(spark, picks).repartition(3).cache()
    inside, keys, fence = greedy._best(df, d, np.zeros(len(d)), 40.0, [], "limit", 50, 3)
    assert isinstance(inside, greedy.Entries) and inside.tids.dtype == np.int32 and len(inside) == len(keys[0]) and fence is not None
    got = greedy.compress(df, d, 40, "limit", "fenced", 100)
    assert got.ids() == reference(picks, d, 40, "limit") and got.passes <= 20
    long = frame(spark, make([(q, 1, {t: 1 for t in range(12)}) for q in range(50)])).cache()
    assert greedy.compress(long, d, 50, 1e-6, pool=1).ids() == list(range(50))


def test_large_parts_are_picked_from_by_passes(spark, monkeypatch):
    picks, d = random_log(17, 90)
    df = frame(spark, picks).cache()
    rows = lambda scope: sorted((r.part, r.pick_no, r.qid) for r in partitioned.local_summaries(df, d, 4, 3, 1e-6, scope=scope).collect())
    small = {s: rows(s) for s in ("global", "local")}
    for most in (0, 29, 31):  # all, some and some other parts go beyond the memory of a task
        monkeypatch.setattr(partitioned, "PART_ENTRIES", most)
        assert {s: rows(s) for s in ("global", "local")} == small
