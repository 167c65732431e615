import numpy as np
import pytest
from pyspark.sql import functions as F

from repsum.functions import numeric, sqltext
from repsum.functions.distance import pairwise
from repsum.operators import advisor, baselines, features
from repsum.plans.catalog import QUERIES
from repsum.sources import templates
from repsum.sources.logs import events_log, orders_log, skewed_log
from repsum.sources.tables import read_log

SF = "/root/testdata/sf0.001"


def test_buckets(spark):
    df = spark.createDataFrame([(1, 5), (2, 10), (3, 20), (4, None), (5, 30), (6, -1)], "qid long, v long")
    got = [r[0] for r in df.orderBy("qid").select(numeric.bucket(F.col("v"), F.lit(5), F.lit(20), 10)).collect()]
    assert got == [0, 3, 10, None, 10, 0]
    assert df.select(numeric.bucket(F.lit(7), F.lit(7), F.lit(7), 10)).head()[0] == 0
    row = numeric.out_of_range(df, {"v": (5, 20)}).head()
    assert (row.below, row.above, row.missing) == (1, 1, 1)


def test_nulls_give_no_token(spark):
    entries = spark.createDataFrame([(1, None, "a"), (2, 3, None)], "qid long, v long, c string")
    assert [tuple(r) for r in features.numeric_tokens(entries, ["v"], 10).collect()] == [(2, "v", "0", 1)]
    assert [r.token for r in features.count_bag(entries, "qid", c=F.col("c")).collect()] == ["a"]


def test_logs_have_their_published_sizes(spark):
    toks = features.tokens(orders_log(spark, SF))
    assert toks.agg(F.sum("mult")).head()[0] == 28_500 and features.frequencies(toks).count() == 2_708
    events = features.tokens(events_log(spark, SF))
    assert events.agg(F.sum("mult")).head()[0] == 7_970 and features.frequencies(events).count() == 902


@pytest.mark.parametrize(
    "sql, want",
    [
        ("SELECT a, AVG(b), MAX(c), MAX(d) FROM T1 GROUP BY a", "AVG MAX MAX | T1 | T1.a | "),
        ("SELECT COUNT(*) FROM T1, T2 WHERE T1.a = T2.a", "COUNT | T1 T2 |  | "),
        ("SELECT * FROM T1, T2, T3 ORDER BY T1.a, T2.b, T3.c", " | T1 T2 T3 |  | T1.a T2.b T3.c"),
        ("with x as (select sum(a) s from t) select x.s from x join u as v on x.k = v.k where v.w in (select k from y) order by 1 desc", "SUM | t u y |  | x.s"),
        ("select upper(m.b) from \"My T\" m where m.d like '%from z%' group by m.d, e -- from q", "UPPER | My T | My T.d My T.e | "),
        ("select rank() over (partition by q order by z) from t /* , u */", "RANK | t |  | "),
        ("select case when a > 1 then lower(b) else 'x' end, b from t order by 2", "LOWER | t |  | t.b"),
        ("select sum(a) from (select a from s.inner_t) as z where extract(year from z.d) = 1", "SUM | s.inner_t |  | "),
        ("call do_it(1, 2)", "DO_IT |  |  | "),
        ("select 1 from a union all select 2 from b", " | a b |  | "),
    ],
)
def test_parser(sql, want):
    got = sqltext.parse(sql)
    shown = " | ".join(" ".join(sorted(t for f, t in got if f == k)) for k in ("function_call", "table_reference", "group_by", "order_by"))
    assert shown == want


def test_templates_are_parsed_as_described():
    for t in templates.REPORTS + templates.STARS:
        for i in (0, 7, 99):
            got = [(f, x) for f, x in sqltext.parse(templates.render(t, i)) if f not in ("where_column", "n_joins")]
            assert sorted(got) == sorted(templates.expected_tokens(t)), t.name
    assert len(templates.REPORTS) == 22 and len(templates.STARS) == 13
    assert all([f for f, _ in t.calls] == ["SUM"] for t in templates.STARS)


def test_rendered_templates_run(spark):
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"):
        spark.read.parquet(f"{SF}/{t}.parquet").createOrReplaceTempView(t)
    for t in templates.REPORTS + templates.STARS:
        sql = templates.render(t, 3)
        if t.name in ("h02", "h15", "h18", "h20"):  # they order by a column outside the aggregate: text features only
            continue
        spark.sql(sql).schema  # noqa: B018


def test_fingerprints(spark):
    log = templates.sql_log(spark, templates.REPORTS[:4], 20)
    assert log.select(sqltext.fingerprint(F.col("sql"))).distinct().count() == 4
    assert sqltext.sql_tokens(log).groupBy("qid").count().count() == 80
    row = spark.createDataFrame([("select 'a' from t where x = 'a' and y = 'b'",)], "sql string").select(sqltext.anonymise(F.col("sql"), "s")).head()[0]
    assert "'a'" not in row and row.count(row.split("'")[1]) == 2


def test_sql_surface(spark):
    sqltext.register(spark)
    got = spark.sql("select * from tokens_of('select max(a) from t')").collect()
    assert ("function_call", "MAX") in [tuple(r) for r in got]


def test_log_readers(spark, tmp_path):
    (tmp_path / "log.csv").write_text("1,select 1,2024-01-01 00:00:00,5,1,2,3,4,0\nnot,a,log\n")
    rows = read_log(spark, str(tmp_path / "log.csv"), "csv").collect()
    assert rows[0].exec_ms == 5 and rows[1].bad_record is not None
    (tmp_path / "log.txt").write_text("select 1\nselect 2\n")
    assert read_log(spark, str(tmp_path / "log.txt"), "text").count() == 2


def points(spark):
    rng = np.random.default_rng(0)
    rows = [(i, (np.array([10.0 * (i % 3), 0.0]) + rng.normal(size=2) * 0.1).tolist(), [f"c{i % 3}", f"x{i % 2}"]) for i in range(30)]
    return spark.createDataFrame(rows, "qid long, num array<double>, toks array<string>")


@pytest.mark.parametrize("kind", ["numeric", "categorical", "mixed"])
def test_clustering_finds_the_clusters(spark, kind):
    p = points(spark)
    medoids, cost = baselines.k_medoids(p, 3, kind)
    assert len(medoids) == 3 and cost >= 0
    if kind != "categorical":
        assert {m % 3 for m in medoids} == {0, 1, 2}
        assert {m % 3 for m in baselines.hierarchical(p, 3, "average", kind)} == {0, 1, 2}
        assert {m % 3 for m in baselines.hierarchical(p, 3, "divisive", kind)} == {0, 1, 2}


def test_distances():
    d = pairwise(np.array([[0.0, 0.0], [3.0, 4.0]]), [{"a": 2, "b": 1}, {"a": 1}], True)
    assert d[0, 1] == pytest.approx((np.sqrt(12.5) + 2 / 3) / 2)


def test_distances_cover_the_whole_tables(spark):
    for name, table in (("euclid_to_chosen", "embeddings"), ("jaccard_to_chosen", "orders")):
        got = QUERIES[name](spark, SF).collect()
        n = spark.read.parquet(f"{SF}/{table}.parquet").count()
        assert n > 60 and len(got) == 8 * n and len({(r.qid, r.other) for r in got}) == 8 * n
        assert len({r.qid for r in got}) == n and all(r.dist == 0 for r in got if r.qid == r.other)
        if table == "embeddings":
            v = {r.vec_id: np.array(r.embedding, float) for r in spark.read.parquet(f"{SF}/{table}.parquet").collect()}
            want = lambda a, b: np.sqrt(((v[a] - v[b]) ** 2).mean())
        else:
            bags = {}
            for r in features.tokens(orders_log(spark, SF)).collect():
                bags.setdefault(r.qid, set()).add((r.feature, r.token))
            want = lambda a, b: 1 - len(bags[a] & bags[b]) / len(bags[a] | bags[b])
        assert all(r.dist == pytest.approx(want(r.qid, r.other), abs=2e-6) for r in got)


def test_methods_are_compared_over_one_whole_log(spark, monkeypatch):
    seen = []

    def clusters(points, k, *_):
        ids = [r.qid for r in points.select("qid").orderBy("qid").collect()]
        seen.append(ids)
        return ids[:k]

    monkeypatch.setattr(baselines, "hierarchical", clusters)
    monkeypatch.setattr(baselines, "k_medoids", lambda points, k, *a, **b: (clusters(points, k), 0.0))
    methods = {r.method for r in QUERIES["compare_methods_shared"](spark, SF).collect()}
    assert {f"{m}_{kind}" for m in ("k_medoids", "hierarchical") for kind in ("numeric", "categorical", "mixed")} <= methods and len(methods) == 11
    sql = templates.sql_log(spark, templates.REPORTS + templates.STARS, 20)
    whole = [r.qid for r in skewed_log(features.Log(sql.select("qid"), sql.select("qid"), [])).entries.orderBy("qid").collect()]
    assert 700 < len(whole) <= baselines.MAX_PAIRWISE and seen == [whole] * 6


def test_sampling(spark):
    e = spark.range(200).withColumnRenamed("id", "qid").withColumn("cost", F.lit(3))
    a, b = (baselines.random_sample(x, 20) for x in (e, e.repartition(7)))
    assert [tuple(r) for r in a.orderBy("pick_no").collect()] == [tuple(r) for r in b.orderBy("pick_no").collect()]
    assert baselines.sample_knapsack(e, 10).count() == 3


def test_advisor_costs(spark):
    shapes = {t.name: advisor.Shape(t.tables, tuple((c, templates.PREDICATES[c].split()[0]) for c in t.where), t.group) for t in templates.STARS}
    w = advisor.Workload(shapes, dict.fromkeys(shapes, 1), {"lineitem": 6000, "orders": 1500, "part": 200, "supplier": 10, "customer": 150}, {"part.p_brand": 25, "part.p_type": 6})
    found = advisor.candidates(w, {"index", "view"})
    none = advisor.whatif_cost(w, [])
    assert all(advisor.whatif_cost(w, [s]) <= none for s in found)
    design, used = advisor.advise(w, {"index", "view"}, 10_000)
    assert used <= 10_000 and advisor.whatif_cost(w, design) < none
    assert advisor.advise(w, {"index"}, 5)[0] == []


def test_advice_from_the_text_of_a_log(spark):
    """Candidates come from parsed texts, whoever wrote them; unknown tables are left out."""
    rows = [(n, sql.format(n)) for n, sql in enumerate(["select o_orderstatus, count(*) from orders where o_totalprice > {} group by o_orderstatus"] * 6 + ["SELECT count(*) FROM orders o WHERE o.o_orderpriority = '{}'"] * 3 + ["select 1 from elsewhere where z = {}"])]
    log = spark.createDataFrame(rows, "qid long, sql string")
    w = advisor.workload(spark, log, {"orders": spark.read.parquet(f"{SF}/orders.parquet")})
    assert sorted(w.counts.values()) == [1, 3, 6]
    found = {(x.kind, x.cols) for x in advisor.candidates(w, {"index", "view"})}
    assert found == {("index", ("orders.o_totalprice",)), ("index", ("orders.o_orderpriority",)), ("view", ("orders.o_orderstatus", "orders.o_totalprice"))}
    assert advisor.whatif_cost(w, []) == 9 * 1500
    assert advisor.whatif_cost(w, [advisor.Structure("index", ("orders",), ("orders.o_orderpriority",))]) == 6 * 1500 + 3 * 300
    assert advisor.whatif_cost(w, advisor.optimal(w, {"index"})) == 6 * (1500 * 333 // 1000) + 3 * 300


def test_greedy_advice_is_the_best_step_each_time(spark):
    shapes = {t.name: advisor.Shape(t.tables, tuple((c, templates.PREDICATES[c].split()[0]) for c in t.where), t.group) for t in templates.REPORTS}
    w = advisor.Workload(shapes, {n: 1 + i % 5 for i, n in enumerate(shapes)}, dict(templates.UNIT_ROWS), {c: 5 + len(c) for t in templates.REPORTS for c in (*t.where, *t.group)})
    design, _ = advisor.advise(w, {"index", "view"}, 1 << 40, 5)
    held = []
    for chosen in design:
        costs = {x: advisor.whatif_cost(w, [*held, x]) for x in advisor.candidates(w, {"index", "view"}) if x not in held}
        assert costs[chosen] == min(costs.values())
        held.append(chosen)


def test_fingerprints_keep_ordinals_and_quoted_names(spark):
    texts = [s.format(1999) for s, _ in templates.ODD_TEXTS]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "qid long, sql string")
    assert df.select(sqltext.mark(F.col("sql"))).distinct().count() == len(texts)
    same = [("select a from t where x in (1, 2) and y = 'b' -- c", "SELECT a\nFROM t WHERE x IN (3,4,5) AND y = 'it''s'"), ("select f(x) from t limit 5", "select f(x) from t limit 6")]
    for a, b in same:
        got = spark.createDataFrame([(a,), (b,)], "sql string").select(sqltext.mark(F.col("sql"))).distinct().count()
        assert got == 1, (a, b)


def test_texts_have_tokens_of_their_own(spark):
    for i, (sql, want) in enumerate(templates.ODD_TEXTS):
        got = sorted((f, t) for f, t in sqltext.parse(sql.format(7), True) if f in ("function_call", "table_reference", "group_by", "order_by"))
        assert got == sorted(templates.odd_tokens(want)), sql
    where = [t for f, t in sqltext.parse("select 1 from t where extract(year from d) = 1 and date '1999-01-01' < e and interval '1' day < f and cast(g as int) is null") if f == "where_column"]
    assert where == ["t.d", "t.e", "t.f", "t.g"]
    assert ("function_call", "P") in sqltext.parse("call p(1)")


def test_no_literal_survives_anonymising(spark):
    sql = "select a, 3.25 from t where ssn = 123456789 and n = 'Bob' and m in (123456789, 7) /* call 555 */ group by 1, a order by 2 limit 10"
    row = spark.createDataFrame([(sql,), (None,)], "sql string").select(sqltext.anonymise(F.col("sql"), "s").alias("x")).collect()
    got = row[0].x
    assert row[1].x is None and not any(x in got for x in ("3.25", "123456789", "Bob", "555"))
    assert "group by 1, a order by 2 limit 10" in got and sqltext.parse(got) == sqltext.parse(sql)
    number = got.split("ssn = ")[1].split()[0]
    assert len(number) == 9 and got.count(number) == 2 and sqltext.scrub(sql, "other") != got


def test_sinks(spark, tmp_path):
    from repsum.sources import sinks

    path = f"file://{tmp_path}/days"
    sinks.write_partitioned(spark.createDataFrame([(1, "a"), (2, "b")], "v long, day string"), path, ["day"])
    sinks.write_partitioned(spark.createDataFrame([(3, "b")], "v long, day string"), path, ["day"])
    assert sorted((r.v, r.day) for r in spark.read.parquet(path).collect()) == [(1, "a"), (3, "b")]
    log = spark.createDataFrame([(1, "select 1 as x"), (2, "select 2 as x"), (3, "select 3 as x")], "qid long, sql string")
    sinks.export_script(spark.createDataFrame([(1, 3), (2, 1)], "pick_no int, qid long"), log, f"file://{tmp_path}/script")
    ran = sinks.run_script(spark, f"file://{tmp_path}/script")
    assert [q for q, _ in ran] == ["select 3 as x", "select 1 as x"] and all(t >= 0 for _, t in ran)


def test_measured_run_with_a_sorted_copy(spark, tmp_path):
    """A range-sorted copy gives the same rows and reads fewer of them for a predicate on its column."""
    lines = spark.read.parquet(f"{SF}/lineitem.parquet")
    copy = advisor.sorted_copy(lines, "l_quantity", f"file://{tmp_path}/copy")
    assert copy.count() == lines.count()
    text = ["select count(*) from lineitem where l_quantity < 5"]
    assert all(advisor.measure(spark, text, {"lineitem": t}) > 0 for t in (lines, copy))
    spans = [sorted(r.l_quantity for r in spark.read.parquet(f).select("l_quantity").collect()) for f in copy.inputFiles()]
    spans = sorted((s[0], s[-1]) for s in spans if s)
    assert all(a[1] <= b[0] for a, b in zip(spans, spans[1:]))


def test_doubling_stops_when_good_enough(spark):
    assert len(baselines.k_medoids_doubling(points(spark), lambda ids: len(ids) >= 3, kind="numeric")) == 4
    assert len(baselines.k_medoids_doubling(points(spark), lambda ids: False, most=4, kind="numeric")) == 4


def test_multiset_and_mixed_distances(spark):
    p = points(spark)
    rows = {r.qid: r for r in p.collect()}
    got = {(r.qid, r.other): r.dist for r in baselines.distances_to(p, p.where("qid < 3"), "mixed").collect()}
    for (a, b), d in got.items():
        x, y = rows[a], rows[b]
        gap = np.sqrt(((np.array(x.num) - np.array(y.num)) ** 2).mean())
        assert d == pytest.approx((gap + 1 - len(set(x.toks) & set(y.toks)) / len(set(x.toks) | set(y.toks))) / 2)
    assert pairwise(None, [{"a": 3, "b": 1}, {"a": 1, "c": 2}], True)[0, 1] == pytest.approx(1 - 1 / 6)


def test_boosting_and_settings(spark):
    from repsum.operators import tuning
    from repsum.plans.prepare import prepare

    p = prepare(orders_log(spark, SF))
    weights, history = tuning.boost_weights(p, 10, 3)
    assert len(history) == 3 and len(weights) == len(p.d) and max(h["rho_l1"] for h in history) >= history[0]["rho_l1"]
    rows = tuning.sweep(p, (1.0, 1e-10), (0.0, 1.0), (5, 10))
    assert len(rows) == 8 and all(0 <= r["score"] <= 1 for r in rows)
    best = tuning.best_setting(rows, 1.0, 10)
    assert best["score"] == max(r["score"] for r in rows if r["beta"] == 1.0 and r["k"] == 10)


def test_plan_tokens_name_the_operators(spark):
    from repsum.functions.plantext import plan_tokens

    spark.range(5).createOrReplaceTempView("five")
    log = spark.createDataFrame([(1, "select id % 2, count(*) from five group by 1"), (2, "select id from five order by id"), (3, "select id from five order by id")], "qid long, sql string")
    got = {(r.qid, r.token) for r in plan_tokens(spark, log).collect()}
    assert (1, "Aggregate") in got and (2, "Sort") in got and (3, "Sort") in got and (2, "Aggregate") not in got


def test_views_and_bucket_in_sql(spark):
    from repsum.plans.prepare import views
    from repsum.sources import logs

    sqltext.register(spark)
    views(logs.orders_log(spark, SF), "surface")
    assert {r.qid for r in spark.sql("SELECT DISTINCT qid FROM surface_tokens").collect()} <= {r.qid for r in spark.table("surface_entries").select("qid").collect()}
    assert spark.table("surface_domain").count() == spark.table("surface_tokens").select("feature", "token").distinct().count()
    got = spark.sql("SELECT token_bucket(v, 0, 10, 4) AS b FROM VALUES (CAST(NULL AS BIGINT)), (-5), (0), (3), (9), (10), (99) AS t(v)").collect()
    assert [r.b for r in got] == [None, 0, 0, 1, 3, 4, 4]
    assert spark.sql("SELECT token_bucket(7, 5, 5, 4) AS b").head().b == 0


def test_statistics_over_jdbc(spark):
    from repsum.sources.tables import read_statistics

    url = "jdbc:derby:memory:statistics;create=true"
    log = [(i, 10.0 * i) for i in range(40)]
    spark.createDataFrame(log, "id long, ms double").write.jdbc(url, "calls", "overwrite")
    got = read_statistics(spark, url, "calls", "id", 0, 40, 4)
    assert got.rdd.getNumPartitions() == 4
    assert sorted(tuple(r) for r in got.collect()) == log


def test_sample_knapsack_takes_the_longest_prefix(spark):
    from repsum.operators import baselines

    costs = {i: (i * 37) % 50 + (1000 if i % 41 == 0 else 0) for i in range(300)}
    e = spark.createDataFrame(list(costs.items()), "qid long, cost long")
    order = [r.qid for r in baselines.random_sample(e, 300).orderBy("pick_no").collect()]
    for budget in (0, 60, 2_000, 9_000, 10**9):
        want, spent = [], 0
        for q in order:
            spent += costs[q]
            if spent > budget:
                break
            want.append(q)
        assert [r.qid for r in baselines.sample_knapsack(e, budget).orderBy("pick_no").collect()] == want
    assert baselines.sample_knapsack(e.where("qid < 0"), 5).count() == 0


@pytest.mark.parametrize("name", ["w_sql_tokens", "w_star_tokens", "w_sql_odd_tokens", "w_sql_where", "w_sql_statistics", "w_sql_joins", "w_sql_fingerprints", "plan_operator_tokens"])
def test_sql_logs_are_over_the_orders_table(spark, tmp_path, name):
    """An order more is an entry more of the log; results equal the SQL's over the same table."""
    import os

    import duckdb

    from repsum.plans.oracle import oracle

    for t in ("region", "nation", "customer", "supplier", "part", "lineitem"):
        os.symlink(f"{SF}/{t}.parquet", tmp_path / f"{t}.parquet")
    db = duckdb.connect()
    db.sql(f"create view orders as select * from '{SF}/orders.parquet' where o_orderkey < 500 or o_orderkey % 7 = 3")
    db.sql(f"copy (select * from orders) to '{tmp_path}/orders.parquet' (format parquet)")
    got = sorted(tuple(r) for r in QUERIES[name](spark, str(tmp_path)).collect())
    if name in oracle():
        assert got == sorted(db.sql(oracle()[name]).fetchall())
    else:
        assert {r[0] for r in got} == {r[0] for r in db.sql("select o_orderkey from orders").fetchall()}


@pytest.mark.parametrize("kind", ["numeric", "categorical", "mixed"])
def test_clusters_are_compared_in_pieces(spark, monkeypatch, kind):
    """Medoids, sums and widest pairs of clusters dealt into pieces; logs beyond a matrix are clustered too."""
    rng = np.random.default_rng(3)
    rows = [(q, rng.normal(size=9 if kind == "numeric" else 2).tolist(), sorted({f"t{t}" for t in rng.integers(0, 6, 1 + q % 3)})) for q in range(80)]
    df = spark.createDataFrame(rows, "qid long, num array<double>, toks array<string>").cache()
    of = spark.createDataFrame([(q, q % 3) for q in range(80)], "qid long, medoid long").cache()
    ids, dist = baselines.distance_matrix(df, kind)
    got = {(r.medoid, r.qid): r for r in baselines.pair_statistics(df, of, kind, 10).collect()}
    assert len(got) == 80
    for (m, q), r in got.items():
        own = dist[q, m::3]
        assert r.total == pytest.approx(own.sum(), abs=1e-5)
        assert r.far == pytest.approx(own.max(), abs=1e-6) and dist[q, r.other] == pytest.approx(r.far, abs=1e-6)
    want = {m: min(range(m, 80, 3), key=lambda q: (round(float(dist[q, m::3].sum()), 6), q)) for m in range(3)}
    assert {r.medoid: r.new for r in baselines.medoid_update(df, of, kind).collect()} == want
    whole = baselines.hierarchical(df, 4, "divisive", kind), baselines.k_medoids(df, 4, kind)
    monkeypatch.setattr(baselines, "MAX_PAIRWISE", 50)
    assert (baselines.hierarchical(df, 4, "divisive", kind), baselines.k_medoids(df, 4, kind)) == whole
