"""Features of query plans: operators, scanned tables and join kinds as tokens."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession, functions as F

from repsum.functions.sqltext import mark

_OPERATOR = re.compile(r"^[\s:+\-*()\d]*([A-Z][A-Za-z]+)", re.MULTILINE)
_JOIN = re.compile(r"\bJoin ([A-Z][A-Za-z]+)")
_SCAN = re.compile(r"\bRelation \[(\w+)#")
#: Texts, different in more than literals, whose plans the driver makes.
MAX_TEXTS = 10_000


def plan_tokens(spark: SparkSession, log: DataFrame) -> DataFrame:
    """(qid, feature, token, mult): operators, join kinds and scanned tables (by their first column) of optimised plans.

    Plans are made on the driver, once for all texts that differ in literals only, and for at most
    ``MAX_TEXTS`` of them: a raw ad-hoc log is summarised first.
    """
    marked = log.select("qid", mark(F.col("sql")).alias("mark"), "sql")
    texts = marked.groupBy("mark").agg(F.min("sql").alias("sql")).limit(MAX_TEXTS + 1).collect()
    if len(texts) > MAX_TEXTS:
        raise ValueError(f"more than {MAX_TEXTS} different texts to plan; summarise the log first")
    rows = []
    for r in texts:
        plan = spark.sql(r["sql"])._jdf.queryExecution().optimizedPlan().toString()
        for feature, found in (("operator", _OPERATOR), ("join", _JOIN), ("scan", _SCAN)):
            rows += [(r["mark"], feature, name) for name in found.findall(plan)]
    counted = spark.createDataFrame(rows, "mark string, feature string, token string").groupBy("mark", "feature", "token").agg(F.count("*").alias("mult"))
    return marked.select("qid", "mark").join(counted, "mark").select("qid", "feature", "token", "mult")
