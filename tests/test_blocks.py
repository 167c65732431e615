import dataclasses

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_greedy import frame, make, random_log, reference

from repsum.operators import blocks, encode, greedy, partitioned
from repsum.plans.catalog import PINNED_EVENTS
from repsum.plans.prepare import prepare
from repsum.sources import logs

SF = "/root/testdata/sf0.001"


def same(a, b):
    assert a.dtypes == b.dtypes and a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


@pytest.mark.parametrize("name,pinned", [("orders", None), ("events", PINNED_EVENTS), ("events", None)])
def test_rows_give_what_tokens_give(spark, name, pinned):
    """A log's rows, met once, give the domain, vectors and tokens that its bags and entries give."""
    log = {"orders": logs.orders_log, "events": logs.events_log}[name](spark, SF)
    a, b = prepare(log, pinned=pinned), prepare(dataclasses.replace(log, rows=None), pinned=pinned)
    assert a.packed is not None and b.packed is None and (a.d == b.d).all()
    for x, y in ((a.domain, b.domain), (a.vectors, b.vectors), (a.tokens, b.tokens)):
        same(x, y)


def test_odd_rows(spark, tmp_path, monkeypatch):
    """Orders without lines, lines without orders, lines without parts, nulls, and entries over several batches."""
    monkeypatch.setattr(encode, "BLOCK", 2)
    o = spark.createDataFrame([(1, 10.0, "A"), (2, None, "B"), (3, 5.5, None), (4, 7.0, "A")], "o_orderkey long, o_totalprice double, o_orderpriority string").withColumn("o_orderdate", F.lit("1995-01-01").cast("timestamp"))
    rows = [(1, 1, 2.0, 1.5, 0.1, 0.02, "R", "F")] * 9 + [(1, 9, 1.0, 2.5, 0.0, 0.0, None, "F"), (2, 2, 3.0, 9.25, 0.05, 0.01, "N", "O"), (4, None, 3.0, 9.25, 0.05, 0.01, "N", "O"), (8, 2, 4.0, 1.25, 0.0, 0.03, "A", "F")]
    li = spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string")
    part = spark.createDataFrame([(1, "x", "t"), (2, "x", None)], "p_partkey long, p_brand string, p_type string")
    for name, df in (("orders", o), ("lineitem", li), ("part", part)):
        df.write.parquet(f"{tmp_path}/{name}.parquet")
    log = logs.orders_log(spark, str(tmp_path))
    a, b = prepare(log), prepare(dataclasses.replace(log, rows=None))
    same(a.vectors, b.vectors)
    same(a.domain, b.domain)
    priced = {r.qid: r.cost for r in prepare(log, cost="n1").vectors.collect()}
    assert priced[1] == 1000 and priced[3] == 550 and priced[2] is None and priced[8] is None


@pytest.mark.parametrize("gamma", [1.0, 1e-25, "limit"])
def test_blocks_are_picked_from_as_rows_are(spark, gamma, monkeypatch):
    monkeypatch.setattr(greedy, "CHUNK", 5)
    picks, d = random_log(23, 150, costs=True)
    df = frame(spark, picks).repartition(3)
    own = blocks.Blocks.of(df)
    same(own.rows(), df)
    assert own.total_cost() == sum(p.cost for p in picks)
    for table in (1 << 22, 0):  # with and without tables of gains
        monkeypatch.setattr(greedy, "TABLE", table)
        for pool in (4, 60):
            assert greedy.compress(own, d, 60, gamma, "fenced", pool, unit=False, safeguard=False).ids() == reference(picks, d, 60, gamma)


def test_wide_numbers_survive_blocks(spark):
    df = frame(spark, make([(-5, 2.5, {70_000: 300, 3: 1}), (1 << 40, 0, {2: 1 << 20})]))
    same(blocks.Blocks.of(df).rows(), df)


def test_passes_serve_all_large_parts(spark, monkeypatch):
    """Large parts share their passes; each had its own run of compress() before."""
    picks, d = random_log(29, 120)
    own = blocks.Blocks.of(frame(spark, picks))
    small = sorted((r.part, r.pick_no, r.qid) for r in partitioned.local_summaries(own, d, 4, 5, 1e-6).collect())
    part = {r.qid: r.part for r in frame(spark, picks).select("qid", partitioned.part_of(5).alias("part")).collect()}
    assert all(part[q] == p for p, _, q in small)
    assert (blocks.hash_of(np.array([p.qid for p in picks])) % 5).tolist() == [part[p.qid] for p in picks]
    monkeypatch.setattr(partitioned, "PART_ENTRIES", 0)
    monkeypatch.setattr(partitioned, "compress", None)
    passes = []
    monkeypatch.setattr(partitioned, "_best_of_parts", lambda *a, f=greedy._best_of_parts: passes.append(1) or f(*a))
    for width in (1 << 16, 20):
        monkeypatch.setattr(partitioned, "PASS_POOL", width)
        assert sorted((r.part, r.pick_no, r.qid) for r in partitioned.local_summaries(own, d, 4, 5, 1e-6).collect()) == small
    assert passes
