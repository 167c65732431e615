"""Readers of the given tables and of query logs, and the engine's schemas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

LOG = T.StructType(
    [
        T.StructField("qid", T.LongType()),
        T.StructField("sql", T.StringType()),
        T.StructField("ts", T.TimestampType()),
        T.StructField("exec_ms", T.LongType()),
        T.StructField("plan_ms", T.LongType()),
        T.StructField("in_bytes", T.LongType()),
        T.StructField("out_rows", T.LongType()),
        T.StructField("cpu_ms", T.LongType()),
        T.StructField("n_joins", T.IntegerType()),
    ]
)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(column: str):
    """A money or rate column as fixed-point long, so that every engine buckets it alike."""
    return F.round(F.col(column) * 100).cast("long")


def read_log(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """A query log of another system; rows that do not parse keep their text in ``bad_record``."""
    if kind in ("parquet", "orc"):
        return spark.read.format(kind).schema(LOG).load(path)
    if kind == "text":
        return spark.read.text(path).select(F.xxhash64("value").alias("qid"), F.col("value").alias("sql"))
    schema = T.StructType(LOG.fields + [T.StructField("bad_record", T.StringType())])
    reader = spark.read.format(kind).schema(schema).option("columnNameOfCorruptRecord", "bad_record").option("mode", "PERMISSIVE")
    return reader.load(path)


def read_statistics(spark: SparkSession, url: str, table: str, key: str, low: int, high: int, parts: int) -> DataFrame:
    """Statistics views of a database over JDBC, read in ``parts`` ranges of ``key``."""
    return spark.read.jdbc(url, table, column=key, lowerBound=low, upperBound=high, numPartitions=parts)
