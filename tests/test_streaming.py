import numpy as np
import pytest
from pyspark.sql import functions as F

from repsum.operators.features import domain, pack, tokens
from repsum.operators.greedy import target_array
from repsum.sources.logs import events_log
from repsum.streaming import monitor

SF = "/root/testdata/sf0.001"


@pytest.fixture
def files(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    for n in range(7):
        part = events.where(F.expr(f"event_id div 143 = {n}"))
        part.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in"), events


def drain(query):
    query.awaitTermination(120)
    assert query.exception() is None


def test_counts_equal_the_batch(spark, files, tmp_path):
    stream, events = files
    drain(monitor.token_counts(stream, "60 days").writeStream.format("memory").queryName("counts").outputMode("complete").option("checkpointLocation", f"{tmp_path}/c1").trigger(availableNow=True).start())
    want = events.groupBy(F.date_trunc("day", "ts").alias("start"), "event_type").agg(F.count("*").alias("n"))
    assert sorted(map(tuple, spark.table("counts").collect())) == sorted(map(tuple, want.collect()))


def test_summaries_of_batches_and_replay(spark, tmp_path):
    log = events_log(spark, SF)
    toks = tokens(log)
    dom = domain(toks)
    vectors = pack(toks, dom)
    for n in range(3):
        vectors.where(F.col("qid") % 3 == n).coalesce(1).write.mode("append").parquet(f"{tmp_path}/v")
    stream = spark.readStream.schema(vectors.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/v")
    d = target_array(dom)
    drain(monitor.start_summaries(stream, f"{tmp_path}/out", f"{tmp_path}/c2", d, 6))
    read = lambda b: [(r.pick_no, r.qid) for r in spark.read.parquet(f"{tmp_path}/out/batch={b}").orderBy("pick_no").collect()]
    first, last = read(0), read(2)
    assert len(first) == len(last) == 6
    again = spark.read.parquet(f"{tmp_path}/v").where(F.col("qid").isin([q for _, q in last]))
    monitor.on_batch(f"{tmp_path}/out", d, 6)(again.limit(0), 3)
    assert {q for _, q in read(3)} == {q for _, q in last}
    monitor.on_batch(f"{tmp_path}/out", d, 6)(again.limit(0), 3)
    assert {q for _, q in read(3)} == {q for _, q in last}
    assert isinstance(d, np.ndarray)


def test_late_rows_are_counted(spark, tmp_path):
    schema = "ts timestamp"
    rows = lambda *t: spark.createDataFrame([(x,) for x in t], "s string").select(F.col("s").cast("timestamp").alias("ts"))
    run = monitor.late_rows(f"{tmp_path}/late", 3600)
    run(rows("2024-01-01 10:00:00"), 0)
    run(rows("2024-01-01 08:00:00", "2024-01-01 09:30:00"), 1)
    run(rows("2024-01-01 08:00:00", "2024-01-01 09:30:00"), 1)
    got = {r.batch: (r.n, r.late) for r in spark.read.parquet(f"{tmp_path}/late").collect()}
    assert got == {0: (1, 0), 1: (2, 1)} and schema
