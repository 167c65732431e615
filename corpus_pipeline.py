"""A corpus pipeline of five operators, each stage written as Parquet and read by the next.

language        rejects texts without a letter, to which no language can be given
near_duplicates keeps one document of each group of SimHash links
decontaminate   drops documents that hold a benchmark passage
mix             repeats or omits documents so that sources meet their target weights
tokens          writes token ids in the plane format and returns where each document lies

A stage keeps every column of its input with its values, whatever names its operator uses inside;
rows that a stage keeps are those of its input. The last stage returns doc_id, start, n_tokens
and ids_crc32. Language models are fitted on the labelled rows of the input that are not held
out; nothing is labelled in an empty table, which passes through empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from repsum.llm import decontaminate, language, mixing, pivots, token_planes
from repsum.llm.columns import carry
from repsum.llm.queries import TOKENIZER
from repsum.plans.scratch import materialise, ship_package

#: Pieces that a worker remembers: fewer than alone, since executors still hold what earlier stages used.
REMEMBER = 300_000


def stage_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship_package(spark)
    model = language.fit(docs.where(~language.held_out()))
    packed, unpack = carry(docs, ["text"])
    return unpack(language.predict(packed, model).where(F.col("lang_pred") != language.NONE))


def stage_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return pivots.keep_one(docs)


def stage_decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship_package(spark)
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    packed, unpack = carry(docs, ["text"])
    return unpack(decontaminate.scan_documents(packed, benchmark).where(F.col("n_hit") == 0))


def stage_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.repeat_documents(docs)


def stage_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return token_planes.tokenise(docs, TOKENIZER, remember=REMEMBER)


STAGES = [
    ("language", stage_language),
    ("near_duplicates", stage_near_duplicates),
    ("decontaminate", stage_decontaminate),
    ("mix", stage_mix),
    ("tokens", stage_tokens),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


#: The language stage fits support vector machines, which SQL cannot express.
ORACLE_SQL = None
