"""Query logs derived from the given tables: each entry stands for a query, its related rows for its tokens."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from repsum.operators.encode import Numbers, Rows
from repsum.operators.features import Log, count_bag
from repsum.sources.tables import cents, read


def orders_log(spark: SparkSession, sf_dir: str) -> Log:
    """An order with its lines; an order without lines keeps empty bags and zero sums."""
    orders = read(spark, sf_dir, "orders")
    lines = read(spark, sf_dir, "lineitem")
    part = read(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type")
    price = cents("l_extendedprice")
    sums = lines.groupBy("l_orderkey").agg(
        F.sum(price * cents("l_tax")).alias("s_tax"),
        F.sum(price).alias("s_price"),
        F.sum(F.col("l_quantity").cast("long")).alias("s_qty"),
        F.sum(price * (100 - cents("l_discount"))).alias("s_net"),
        F.count("*").alias("s_lines"),
    )
    joined = orders.join(sums, orders["o_orderkey"] == sums["l_orderkey"], "left")
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long")
    entries = joined.select(
        F.col("o_orderkey").alias("qid"),
        F.col("o_orderdate").cast("timestamp").alias("ts"),
        F.col("o_orderpriority").alias("ob"),
        cents("o_totalprice").alias("n1"),
        zero("s_tax").alias("n2"),
        zero("s_price").alias("n3"),
        zero("s_qty").alias("n4"),
        zero("s_net").alias("n5"),
        F.greatest(zero("s_lines") - 1, F.lit(0)).cast("long").alias("n6"),
    )
    per_line = lines.join(part, lines["l_partkey"] == part["p_partkey"], "left")
    bags = count_bag(per_line, "l_orderkey", fn=F.concat("l_returnflag", "l_linestatus"), tb=F.col("p_brand"), gb=F.col("p_type"))
    single = orders.select(F.col("o_orderkey").alias("qid"), F.lit("ob").alias("feature"), F.col("o_orderpriority").alias("token"), F.lit(1).cast("long").alias("mult")).where(F.col("token").isNotNull())
    of_line = F.struct(
        F.concat("l_returnflag", "l_linestatus").alias("fn"), F.col("p_brand").alias("tb"), F.col("p_type").alias("gb"), F.lit(None).cast("string").alias("ob"),
        F.lit(None).cast("long").alias("total"), (price * cents("l_tax")).alias("tax"), price.alias("price"), F.col("l_quantity").cast("long").alias("qty"), (price * (100 - cents("l_discount"))).alias("net"), F.lit(True).alias("line"),
    )
    of_order = F.struct(*(F.lit(None).cast("string").alias(c) for c in ("fn", "tb", "gb")), F.col("o_orderpriority").alias("ob"), cents("o_totalprice").alias("total"), *(F.lit(None).cast("long").alias(c) for c in ("tax", "price", "qty", "net")), F.lit(False).alias("line"))
    # the parts of a task are a small table: no need to sort the lines for them
    with_part = lines.join(part.hint("shuffle_hash"), lines["l_partkey"] == part["p_partkey"], "left")
    rows = with_part.select(F.col("l_orderkey").alias("qid"), of_line.alias("x")).unionByName(orders.select(F.col("o_orderkey").alias("qid"), of_order.alias("x"))).select("qid", "x.*")
    return Log(entries, bags.unionByName(single), ["n1", "n2", "n3", "n4", "n5", "n6"], Rows(rows, ["fn", "tb", "gb"], ["ob"], _order_numbers))


def _order_numbers(table: pa.Table, entry: np.ndarray, start: np.ndarray) -> Numbers:
    """n1 to n6 of the rows that are orders, from those that are their lines."""
    column = lambda name: table.column(name).combine_chunks().fill_null(0).to_numpy()
    line = table.column("line").combine_chunks().to_numpy(zero_copy_only=False)
    at, known = np.flatnonzero(~line), table.column("total").combine_chunks().is_valid().to_numpy(zero_copy_only=False)
    priced = np.flatnonzero(~line & known)
    found = {"n1": (entry[priced], column("total")[priced])}
    for name, source in (("n2", "tax"), ("n3", "price"), ("n4", "qty"), ("n5", "net")):
        found[name] = entry[at], np.add.reduceat(column(source), start)[entry[at]]
    found["n6"] = entry[at], np.maximum(np.add.reduceat(line.astype(np.int64), start) - 1, 0)[entry[at]]
    return found


def events_log(spark: SparkSession, sf_dir: str) -> Log:
    """An event in time order with its user's previous event."""
    events = read(spark, sf_dir, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    before = Window.partitionBy("user_id").orderBy("t", "event_id")
    day = Window.partitionBy("user_id", F.to_date("ts")).orderBy("t", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    wide = events.select(
        F.col("event_id").alias("qid"),
        F.col("ts").cast("timestamp").alias("ts"),
        F.col("event_type").alias("type"),
        F.concat_ws("→", F.lag("event_type").over(before), "event_type").alias("pair"),
        F.lag("event_type").over(before).isNotNull().alias("has_previous"),
        F.hour("ts").alias("hour"),
        F.col("user_id").alias("user"),
        cents("value").alias("value"),
        F.get_json_object("props", "$.k").cast("long").alias("k"),
        F.expr("t div 1000").alias("ms"),
        F.lag(F.expr("t div 1000")).over(before).alias("previous_ms"),
        F.count("*").over(day).alias("run"),
    ).withColumn("gap", F.col("ms") - F.col("previous_ms"))
    bags = count_bag(wide, "qid", type=F.col("type"), bigram=F.when(F.col("has_previous"), F.col("pair")), hour=F.col("hour"), user=F.col("user"))
    rows = wide.select("qid", "type", F.when(F.col("has_previous"), F.col("pair")).alias("bigram"), F.col("hour").cast("string").alias("hour"), F.col("user").cast("string").alias("user"), "value", "k", "gap", "run")
    return Log(wide.select("qid", "ts", "value", "k", "gap", "run"), bags, ["value", "k", "gap", "run"], Rows(rows, ["type", "bigram", "hour", "user"], [], _event_numbers))


def _event_numbers(table: pa.Table, entry: np.ndarray, start: np.ndarray) -> Numbers:
    found = {}
    for name in ("value", "k", "gap", "run"):
        column = table.column(name).combine_chunks()
        at = np.flatnonzero(column.is_valid().to_numpy(zero_copy_only=False))
        found[name] = entry[at], column.take(pa.array(at)).to_numpy()
    return found


def docs_log(spark: SparkSession, sf_dir: str) -> Log:
    """A document with its words: the large-domain log."""
    docs = read(spark, sf_dir, "documents")
    words = docs.select(F.col("doc_id").alias("qid"), F.explode(F.split(F.lower("text"), " ")).alias("w"))
    bags = count_bag(words, "qid", word=F.col("w"))
    single = docs.select(F.col("doc_id").alias("qid"), F.explode(F.array(F.struct(F.lit("lang").alias("f"), F.col("lang").alias("t")), F.struct(F.lit("source").alias("f"), F.col("source").alias("t")))).alias("x"))
    single = single.select("qid", F.col("x.f").alias("feature"), F.col("x.t").alias("token"), F.lit(1).cast("long").alias("mult")).where(F.col("token").isNotNull())
    entries = docs.select(F.col("doc_id").alias("qid"), "n_chars", F.size(F.split("text", "\n")).cast("long").alias("n_lines"), F.size(F.split("text", " ")).cast("long").alias("n_words"))
    return Log(entries, bags.unionByName(single), ["n_chars", "n_lines", "n_words"])


def conversations_log(spark: SparkSession, sf_dir: str) -> Log:
    """A conversation with the roles and opening letters of its turns."""
    turns = read(spark, sf_dir, "conversations")
    first = F.lower(F.substring("text", 1, 1))
    bags = count_bag(turns, "conv_id", role=F.col("role"), opening=F.when(first.rlike("^[aeiou]"), "vowel").when(first.rlike("^[a-z]"), "consonant").otherwise("other"))
    entries = turns.groupBy(F.col("conv_id").alias("qid")).agg(F.count("*").alias("turns"), F.sum(F.length("text")).cast("long").alias("chars"))
    return Log(entries, bags, ["turns", "chars"])


def pages_log(spark: SparkSession, sf_dir: str) -> Log:
    """A web page with its host, path segments, query keys and tag names."""
    pages = read(spark, sf_dir, "pages")
    host = F.regexp_extract("url", r"^https?://([^/?#]*)", 1)
    path = F.regexp_extract("url", r"^https?://[^/?#]*([^?#]*)", 1)
    query = F.regexp_extract("url", r"\?([^#]*)", 1)
    segments = F.filter(F.split(path, "/"), lambda s: s != "")
    keys = F.transform(F.filter(F.split(query, "&"), lambda s: s != ""), lambda s: F.substring_index(s, "=", 1))
    tags = F.regexp_extract_all(F.col("html"), F.lit(r"<([a-z][a-z0-9]*)"), F.lit(1))
    each = lambda name, values: F.transform(values, lambda v: F.struct(F.lit(name).alias("feature"), v.alias("token")))
    long = pages.select(F.col("page_id").alias("qid"), F.explode(F.concat(each("host", F.array(host)), each("segment", segments), each("key", keys), each("tag", tags))).alias("t")).select("qid", "t.feature", "t.token")
    bags = long.groupBy("qid", "feature", "token").agg(F.count("*").alias("mult"))
    entries = pages.select(F.col("page_id").alias("qid"), F.length("html").cast("long").alias("n_html"), F.regexp_count("html", F.lit("<a ")).cast("long").alias("n_links"))
    return Log(entries, bags, ["n_html", "n_links"])


def embeddings_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(qid, label, num): vectors with their true cluster, for the numeric clustering baselines."""
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("qid"), "label", F.transform("embedding", lambda x: x.cast("double")).alias("num"))


def toy_tokens(spark: SparkSession) -> DataFrame:
    """The three-query worked example with ten buckets, as tokens."""
    rows = [
        (1, "fn", "AVG", 1), (1, "fn", "MAX", 2), (1, "tb", "T1", 1), (1, "gb", "T1.a", 1),
        (2, "fn", "COUNT", 1), (2, "tb", "T1", 1), (2, "tb", "T2", 1),
        (3, "tb", "T1", 1), (3, "tb", "T2", 1), (3, "tb", "T3", 1), (3, "ob", "T1.a", 1), (3, "ob", "T2.b", 1), (3, "ob", "T3.c", 1),
    ]
    bags = spark.createDataFrame(rows, "qid long, feature string, token string, mult long")
    stats = spark.createDataFrame([(1, 5, 4, 5, 100, 2, 0), (2, 10, 2, 10, 1000, 3, 1), (3, 8, 5, 20, 500, 4, 2)], "qid long, n1 long, n2 long, n3 long, n4 long, n5 long, n6 long")
    from repsum.operators.features import tokens

    return tokens(Log(stats, bags, ["n1", "n2", "n3", "n4", "n5", "n6"]), 10)


def skewed_log(log: Log, classes: int = 6) -> Log:
    """The log with entries of low hash classes repeated: class c of ``classes`` stands 2^c times.

    Repeats get ids of their own (qid * 64 + copy), since every log entry can be chosen once.
    """
    grade = F.pmod(F.conv(F.substring(F.md5(F.col("qid").cast("string")), 1, 6), 16, 10).cast("long"), F.lit(1 << classes))
    times = F.when(grade == 0, 1 << (classes - 1)).when(grade < 4, 8).when(grade < 16, 2).otherwise(1)
    copies = lambda df: df.withColumn("_c", F.explode(F.sequence(F.lit(0), times - 1))).withColumn("qid", F.col("qid") * 64 + F.col("_c")).drop("_c")
    return Log(copies(log.entries), copies(log.bags), log.numeric)
