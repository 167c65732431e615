"""Where summaries, counts and scripts go."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def write_partitioned(df: DataFrame, path: str, by: list[str]) -> None:
    """Parquet by day or batch; a batch that is written again replaces its own partitions only."""
    df.write.partitionBy(*by).option("partitionOverwriteMode", "dynamic").mode("overwrite").parquet(path)


def export_script(summary: DataFrame, log: DataFrame, path: str) -> None:
    """The summary as one SQL script in pick order. A summary is small by definition."""
    chosen = log.join(F.broadcast(summary.select("pick_no", "qid")), "qid").select("pick_no", F.concat("sql", F.lit(";")).alias("line"))
    chosen.repartition(1).sortWithinPartitions("pick_no").select("line").write.mode("overwrite").text(path)


def run_script(spark, path: str) -> list[tuple[str, float]]:
    """Run an exported summary: (text, seconds) of each query."""
    import time

    out = []
    for r in spark.read.text(path).collect():
        sql = r["value"].rstrip(";")
        t = time.perf_counter()
        spark.sql(sql).write.format("noop").mode("overwrite").save()
        out.append((sql, time.perf_counter() - t))
    return out
