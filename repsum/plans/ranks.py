"""Gapless positions without gathering a group in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from repsum.plans.scratch import materialise

_PART_BITS = 33  # monotonically_increasing_id keeps the row's index in its low 33 bits


def positions(df: DataFrame, group: list[str], order: list[str], out: str) -> DataFrame:
    """Append ``out``: 0, 1, ... within each group in the given order.

    Rows are range-partitioned and sorted once and written with their place; the rows of each
    (group, partition) are counted, and the counts before a partition are its offset. The
    offsets have at most one row per partition and group, far fewer than the rows.
    """
    ordered = df.repartitionByRange(*group, *order).sortWithinPartitions(*group, *order)
    placed = materialise(ordered.withColumn("_at", F.monotonically_increasing_id()), "placed").withColumn("_part", F.shiftright("_at", _PART_BITS))
    keys = [f"_g{i}" for i in range(len(group))]
    named = placed.select("*", *(F.col(g).alias(k) for g, k in zip(group, keys)))
    counts = named.groupBy(*keys, "_part").agg(F.count("*").alias("_n"), F.min("_at").alias("_first"))
    before = Window.partitionBy(*keys).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(*(F.col(k).alias(f"{k}o") for k in keys), F.col("_part").alias("_po"), (F.coalesce(F.sum("_n").over(before), F.lit(0)) - F.col("_first")).alias("_shift"))
    on = [F.col(k).eqNullSafe(F.col(f"{k}o")) for k in keys] + [F.col("_part") == F.col("_po")]
    joined = named.join(offsets, on)
    return joined.withColumn(out, F.col("_at") + F.col("_shift")).drop("_at", "_part", "_po", "_shift", *keys, *(f"{k}o" for k in keys))
