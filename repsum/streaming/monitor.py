"""Structured Streaming: summaries, counts and drift of a growing log.

A micro-batch merges its entries with the summary so far and writes everything below
``batch=<id>``. A batch that is replayed overwrites its own folder and starts from the folder of
the batch before, so its output does not change. Entries that arrive after the watermark are
counted to a side table.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming import StreamingQuery

from repsum.operators.greedy import GAMMA, Pick
from repsum.operators.partitioned import _local

SUMMARY = "pick_no int, qid long, gain double, cost double, tids array<int>, mults array<int>"


def _picks(rows) -> list[Pick]:
    return [Pick(r["qid"], 0.0, r["cost"], np.array(r["tids"], np.int64), np.array(r["mults"], np.int64)) for r in rows]


def _exists(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)


def on_batch(out: str, d: np.ndarray, budget: int, pool: int = 4096, gamma=GAMMA) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function over (qid, cost, tids, mults).

    The batch's own summary is made where its rows lie; only summaries meet on the driver.
    """

    def run(df: DataFrame, batch: int) -> None:
        from repsum.operators.greedy import compress

        spark = df.sparkSession
        last = f"{out}/batch={batch - 1}"
        held = _picks(spark.read.schema(SUMMARY).parquet(last).orderBy("pick_no").collect()) if batch and _exists(spark, last) else []
        vectors = df.select("qid", "cost", "tids", "mults").cache()
        new = compress(vectors, d, budget, gamma, pool=pool).picks
        vectors.unpersist()
        merged = _local([*held, *new], d, budget, True, gamma).picks
        rows = [(n, int(p.qid), float(p.gain), float(p.cost), p.tids.tolist(), p.mults.tolist()) for n, p in enumerate(merged, 1)]
        spark.createDataFrame(rows, SUMMARY).coalesce(1).write.mode("overwrite").parquet(f"{out}/batch={batch}")

    return run


def start_summaries(vectors: DataFrame, out: str, checkpoint: str, d: np.ndarray, budget: int, once: bool = True) -> StreamingQuery:
    writer = vectors.writeStream.foreachBatch(on_batch(out, d, budget)).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer).start()


def token_counts(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """(start, event_type, n) per day of a stream of (ts timestamp, event_type)."""
    return events.withWatermark("ts", delay).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding_counts(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.window("ts", "7 days", "1 day")).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    """(user_id, start, end, n) of each user's sessions."""
    return events.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def first_seen(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events whose id has not been seen within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def late_rows(out: str, delay_seconds: int) -> Callable[[DataFrame, int], None]:
    """foreachBatch function that counts rows older than the newest time of all batches before, less the delay."""

    def run(df: DataFrame, batch: int) -> None:
        spark = df.sparkSession
        marks = spark.read.parquet(out).where(F.col("batch") < batch).agg(F.max("newest")).head()[0] if batch and _exists(spark, out) else None
        late = F.count_if(F.col("ts").cast("double") < F.lit(marks) - delay_seconds) if marks is not None else F.lit(0).cast("long")
        df.agg(F.max(F.col("ts").cast("double")).alias("newest"), F.count("*").alias("n"), late.alias("late")).write.mode("overwrite").parquet(f"{out}/batch={batch}")

    return run
