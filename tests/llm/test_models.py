import random

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import Window, functions as F
from cases import odd_rows

from repsum.llm import additive, importance, language

SYLLABLES = {"en": "the an er ing th is", "de": "sch ich ung ein er te", "fr": "eau ique la ent oi re", "es": "ción ado ar os la en", "xx": "qq zz kk vv"}


def sample(n, seed=0):
    rng = random.Random(seed)
    out = []
    for i in range(n):
        lang = rng.choice(list(SYLLABLES))
        s = SYLLABLES[lang].split()
        out.append((i, " ".join("".join(rng.choice(s) for _ in range(rng.randint(1, 4))) for _ in range(rng.randint(5, 50))), lang, "s"))
    return out


def test_held_out_accuracy(documents):
    df = documents(sample(500))
    model = language.fit(df.where(~language.held_out()))
    got = language.predict(df, model).withColumn("out", language.held_out()).where("out").collect()
    assert len(got) > 80 and sum(r.lang == r.lang_pred for r in got) / len(got) >= 0.97
    assert all(0 <= float(r.score) <= 1 for r in got) and set(model.families) == {"germanic", "romance", "only:xx"}


def test_language_of_odd_rows(documents, odd, empty):
    model = language.fit(documents(sample(200)))
    got = {(r.doc_id, r.text): (r.lang_pred, r.score) for r in language.predict(odd, model).collect()}
    for key, (lang, score) in got.items():
        letters = key[1] is not None and any(c.isalpha() for c in key[1])
        assert (lang == "und") == (not letters) and (letters or score == 0)
    assert language.fit(empty) is None
    assert {r.lang_pred for r in language.predict(odd, None).collect()} == {"und"}
    assert language.predict(empty, model).count() == 0


def slow_features(text):
    """Shares of hashed two- and three-byte grams, counted one by one."""
    raw = " ".join(["", *"".join(c if c.isascii() and c.isalpha() or not c.isascii() else " " for c in "".join(c.lower() if c.isascii() else c for c in text)).encode().decode().split(" "), ""])
    raw = b" " + b" ".join(raw.encode().split()) + b" "
    counts = {}
    for i in range(len(raw)):
        if i + 2 < len(raw) + (len(raw) == 2):
            two = (raw[i] * 257 + raw[i + 1]) % (1 << 32)
            grams = [two] if i + 2 >= len(raw) else [two, (two * 263 + raw[i + 2]) % (1 << 32)]
            if len(raw) > 2 and i == len(raw) - 3:
                grams.append((raw[i + 1] * 257 + raw[i + 2]) % (1 << 32))
            for g in grams:
                b = (g * 2654435761) % (1 << 32) >> 20
                counts[b] = counts.get(b, 0) + 1
    total = sum(counts.values())
    return {b: (n / total) ** 0.5 for b, n in counts.items()}


def test_predictions_equal_a_brute_force_model(documents):
    """Each text's features, its family and its duels, counted by hand from the fitted weights."""
    rows = sample(160, 5) + [(900, "x", "en", "s"), (901, "ÀÉ 12", "fr", "s")]
    model = language.fit(documents(rows))
    got = {r.doc_id: r.lang_pred for r in language.predict(documents(rows), model).collect()}
    for i, text, *_ in rows:
        v = slow_features(text)
        margin = lambda w: sum(w[b] * x for b, x in v.items()) + w[-1]
        family = max(range(len(model.families)), key=lambda f: margin(model.family_weights[:, f]))
        own, pairs, weights = model.duels[model.families[family]]
        wins = {x: [0, 0.0] for x in own}
        for n, (a, b) in enumerate(pairs):
            m = margin(weights[:, n])
            wins[own[a] if m >= 0 else own[b]][0] += 1
            wins[own[a]][1] += m
            wins[own[b]][1] -= m
        assert got[i] == min(own, key=lambda x: (-wins[x][0], -wins[x][1], x)), text


def test_training_rows_are_those_of_smallest_hash(spark, documents):
    rows = sample(700, 2)
    df = documents(rows)
    hashes = {r.doc_id: r.h for r in df.select("doc_id", F.xxhash64("doc_id").alias("h")).collect()}
    got = {(r.label, bytes(r.vector)) for r in language.training_rows(df, total=200).collect()}
    want = set()
    for label in SYLLABLES:
        mine = sorted((hashes[i], i, t) for i, t, lang, _ in rows if lang == label)[:40]
        want |= {(label, language.features(t).tobytes()) for *_, t in mine}
    assert got == want


def test_prediction_ignores_labels(documents):
    rows = sample(150)
    model = language.fit(documents(rows))
    a = {r.doc_id: r.lang_pred for r in language.predict(documents(rows), model).collect()}
    b = {r.doc_id: r.lang_pred for r in language.predict(documents([(i, t, None, "other") for i, t, *_ in rows]), model).collect()}
    assert a == b


def brute_neighbours(rows, want):
    ok = [(i, np.array(v, float)) for i, v in rows if v is not None and None not in v and np.isfinite(v).all() and np.any(v) and len(v) == 8]
    out = {}
    for q, x in ok:
        if q % 20 == 0:
            near = sorted(((-(float((x * y).sum())), i) for k, (i, y) in enumerate(ok) if i != q))[:want]
            out.setdefault(q, [i for _, i in near])
    return out


def test_search_recall_and_rules(spark):
    rng = np.random.default_rng(6)
    centres = rng.normal(size=(12, 8))
    rows = [(i, (centres[i % 12] + 0.4 * rng.normal(size=8)).astype(np.float32).tolist()) for i in range(900)]
    rows += [(2000 + i, rows[5][1]) for i in range(40)]
    odd = [(3000, None), (3020, [0.0] * 8), (3040, [float("nan")] * 8), (3060, [1.0, None] + [0.0] * 6), (3080, [1.0] * 7), (None, [1.0] * 8), (3100, [float("inf")] + [0.0] * 7)]
    df = spark.createDataFrame([(i, v, "x") for i, v in rows + odd], "vec_id long, embedding array<float>, score string")
    got = {}
    for r in additive.search(df, lambda v: v % 20 == 0).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    want = brute_neighbours(rows, 20)
    assert set(got) == set(want)
    hits = 0
    held = {i: np.array(v, float) for i, v in rows}
    for q, found in got.items():
        found.sort()
        assert [n for n, *_ in found] == list(range(1, 21))
        assert all(s == pytest.approx(float((held[q] * held[i]).sum()), abs=1e-12) for _, i, s in found)
        assert [(-s, i) for _, i, s in found] == sorted((-s, i) for _, i, s in found)
        hits += len({i for _, i, _ in found} & set(want[q]))
    assert hits / (20 * len(want)) >= 0.95


def test_coarse_codes_lose_no_row(spark):
    """One task scans many more rows than the shortlist holds, and its codes tell little."""
    x = np.random.default_rng(8).normal(size=(8000, 24))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    index, books = additive.build_index(additive.usable(df), 2, 16, 500)
    asked = np.arange(0, 400, 20)
    got = {}
    for r in additive.search_block(index.coalesce(1), books, asked, x[asked], 20).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append(r.vec_id)
    exact = (x @ x[asked].T).T
    exact[np.arange(len(asked)), asked] = -np.inf
    assert got == {q: np.argsort(-s)[:20].tolist() for q, s in zip(asked.tolist(), exact)}


def test_repeated_queries_are_one_query(spark):
    x = np.random.default_rng(2).normal(size=(60, 4)).astype(np.float32)
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    df = spark.createDataFrame(rows + [rows[20], (40, [9.0] * 4), rows[7]], "vec_id long, embedding array<float>")
    got = {}
    for r in additive.search(df, lambda v: v % 20 == 0).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id))
    held = [(i, np.array(v, np.float64)) for i, v in rows + [rows[20], (40, [9.0] * 4), rows[7]]]
    for q, found in got.items():
        asked = min(v.tolist() for i, v in held if i == q)
        near = sorted((-sum(a * b for a, b in zip(asked, v)), i) for i, v in held if i != q)[:20]
        assert [i for _, i in sorted(found)] == [i for _, i in near] and [n for n, _ in sorted(found)] == list(range(1, 21))


def test_recall_at_size_in_few_and_many_tasks(spark):
    """65,536 rows of a hard kind (no clusters): the result is brute force's, however many tasks share the rows."""
    x = np.random.default_rng(4).normal(size=(1 << 16, 16)).astype(np.float32)
    df = spark.createDataFrame(pd.DataFrame({"vec_id": np.arange(len(x)), "embedding": x.tolist()}), "vec_id long, embedding array<float>")
    index, books = additive.build_index(additive.usable(df), 4, 64, 2048)
    asked = np.arange(0, 40 * 1600, 1600)
    exact = x[asked].astype(float) @ x.astype(float).T
    exact[np.arange(len(asked)), asked] = -np.inf
    want = {int(q): set(np.argsort(-s)[:20].tolist()) for q, s in zip(asked, exact)}
    for tasks in (1, 16):
        got = {}
        for r in additive.search_block(index.repartition(tasks), books, asked, x[asked].astype(float), 20).collect():
            got.setdefault(r.query_id, set()).add(r.vec_id)
        assert sum(len(got[q] & want[q]) for q in want) / (20 * len(want)) == 1.0


def test_search_of_few_and_none(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.5, 0.5]), (2, [1.0, 0.0])], "vec_id long, embedding array<float>")
    assert [(r.query_id, r["rank"], r.vec_id) for r in additive.search(df, lambda v: v % 20 == 0).orderBy("rank").collect()] == [(0, 1, 2), (0, 2, 1)]
    assert additive.search(df.where("vec_id < 0"), lambda v: v % 20 == 0).count() == 0


def test_codes_beat_plain_rounding():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(600, 8))
    books = additive.train(x, 4, 16)
    codes = additive.encode(x, books, 8)
    one = additive.encode(x, books, 1)
    error = lambda c: ((x - additive.decode(c, books)) ** 2).sum()
    assert error(codes) <= error(one) and error(codes) < 0.3 * (x**2).sum()


def test_importance(spark, documents):
    rng = random.Random(3)
    good = [(i, " ".join(rng.choice("calm river stone tree light".split()) for _ in range(30)), "en", "s") for i in range(120)]
    bad = [(1000 + i, " ".join(rng.choice("$$$ &&& CLICK!! calm ***".split()) for _ in range(30)), "en", "s") for i in range(80)]
    df = documents(good + bad)
    target = spark.createDataFrame([(i,) for i in range(0, 120, 2)], "doc_id long")
    got = importance.resample(df, target, 0.6).collect()
    assert sum(r.selected for r in got) == 120 and len(got) == 200
    assert sum(r.selected for r in got if r.doc_id < 1000) >= 115
    assert sorted(r["rank"] for r in got) == list(range(200))
    assert [tuple(r) for r in importance.resample(df.repartition(5), target, 0.6).orderBy("rank").collect()] == sorted((tuple(r) for r in got), key=lambda r: r[3])


def test_importance_follows_the_models(spark, documents):
    df = documents([(1, "a b a", "en", "s"), (2, "c d", "en", "s"), (3, None, "en", "s")])
    target = spark.createDataFrame([(1,)], "doc_id long")
    counts = np.zeros((2, importance.BUCKETS), np.int64)
    for text, is_target in (("a b a", True), ("c d", False)):
        for b in importance.grams(text):
            counts[1][b] += 1
            counts[0][b] += is_target
    ratio = importance.log_ratio(counts)
    got = {r.doc_id: r.log_importance for r in importance.importances(df, target).collect()}
    for doc, text in ((1, "a b a"), (2, "c d")):
        at = importance.grams(text)
        assert got[doc] == pytest.approx(ratio[at].sum())
    assert got[3] == 0


def test_draw_follows_the_importances(spark):
    """Over many seeds, rows are drawn as often as by drawing one after another in proportion to weight."""
    weights = {1: 1.0, 2: 2.0, 3: 4.0, 4: 0.5, 5: 3.0}
    total = sum(weights.values())
    first = {i: w / total for i, w in weights.items()}
    chance = {i: first[i] + sum(first[j] * weights[i] / (total - weights[j]) for j in weights if j != i) for i in weights}
    rounds = 8000
    rows = spark.createDataFrame([(i, float(np.log(w))) for i, w in weights.items()], "doc_id long, log_importance double")
    keys = rows.crossJoin(spark.range(rounds).withColumnRenamed("id", "seed")).withColumn("key", F.col("log_importance") + importance.gumbel(F.col("doc_id"), F.col("seed")))
    drawn = keys.withColumn("n", F.row_number().over(Window.partitionBy("seed").orderBy(F.desc("key")))).where("n <= 2")
    got = {r.doc_id: r["count"] / rounds for r in drawn.groupBy("doc_id").count().collect()}
    assert all(abs(got[i] - chance[i]) < 0.02 for i in weights)


def test_selection_equals_a_brute_force_draw(spark, documents):
    rng = random.Random(4)
    rows = [(i, " ".join(rng.choice("aa bb cc dd ee ff".split()) for _ in range(rng.randint(0, 3))), "en", "s") for i in range(60)]
    target = spark.createDataFrame([(i,) for i in range(0, 60, 3)], "doc_id long")
    got = importance.resample(documents(rows), target, 0.25, seed=3).collect()
    counts = np.zeros((2, importance.BUCKETS), np.int64)
    for i, text, *_ in rows:
        np.add.at(counts[1], importance.grams(text), 1)
        if i % 3 == 0:
            np.add.at(counts[0], importance.grams(text), 1)
    p = (counts + 1.0) / (counts.sum(1, keepdims=True) + importance.BUCKETS)
    noise = {r.doc_id: r.g for r in spark.createDataFrame([(i,) for i in range(60)], "doc_id long").select("doc_id", importance.gumbel(F.col("doc_id"), 3).alias("g")).collect()}
    key = {i: sum(float(np.log(p[0][b] / p[1][b])) for b in importance.grams(text)) + noise[i] for i, text, *_ in rows}
    order = sorted(key, key=lambda i: (-key[i], i))
    assert [r.doc_id for r in sorted(got, key=lambda r: r["rank"])] == order
    assert {r.doc_id for r in got if r.selected} == set(order[:15])
    plain = sorted(key, key=lambda i: (noise[i] - key[i], i))[:15]
    assert set(plain) != set(order[:15])  # the noise decides too


def test_importance_of_odd_and_empty(spark, odd, empty):
    none = spark.createDataFrame([], "doc_id long")
    assert {r.log_importance for r in importance.resample(odd, none, 0.5).collect()} == {0.0}
    assert importance.resample(odd, none, 0.5).where("selected").count() == -(-len(odd_rows()) // 2)
    assert importance.resample(empty, none, 0.5).count() == 0


def test_search_in_blocks_equals_brute_force(spark, monkeypatch):
    """Small blocks of rows, queries and pairs; random vectors, a group of equal ones, one of a thousand times the length."""
    monkeypatch.setattr(additive, "SCAN_ROWS", 100)
    monkeypatch.setattr(additive, "QUERIES_AT_ONCE", 7)
    monkeypatch.setattr(additive, "PAIRS_AT_ONCE", 50)
    rng = np.random.default_rng(5)
    x = rng.normal(size=(900, 16))
    x[300:360], x[40] = x[20], 1000 * x[41]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    index, books = additive.build_index(additive.usable(df), 4, 32, 500)
    asked = np.arange(0, 900, 20)
    found: dict = {}
    for r in additive.search_block(index.coalesce(1), books, asked, x[asked], 20, 40).orderBy("query_id", "rank").collect():
        found.setdefault(r.query_id, []).append((r.vec_id, r.score))
    for q in asked.tolist():
        score = x[:, 0] * x[q, 0]
        for d in range(1, 16):
            score += x[:, d] * x[q, d]
        want = [i for i in np.lexsort((np.arange(900), -score)).tolist() if i != q][:20]
        assert found[q] == [(i, score[i]) for i in want]
