"""Mixing sources to target weights by a low-discrepancy schedule, in DataFrame operations only.

Each source's documents are put in a seeded order and laid end to end as a stream of words,
cut into blocks of equal length. Slot i of the schedule has the point frac(i * golden ratio);
the points are spread evenly, so mapping them through the cumulative targets gives every
source its share of any run of slots. A slot's rank among those of its source names the block
it takes, starting again after the last; no block is taken more than ``most`` times.

Targets: sources by code point, null last, get the weights in turn; together they share
``share`` times all words. A target stops at ``most`` times its source's words and the excess
goes to the others by weight until none is above (computed at once, as the water level at
which the capped sources are exactly those below it).

Edge cases: a null text has no words; documents without words take part with taken 0; a
source without words has target 0; repeated rows are rows of their own; an empty table gives
an empty result; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window, functions as F

from repsum.llm.columns import carry
from repsum.plans.scratch import materialise

#: Weights in turn, share of all words, most takes, fractional golden ratio.
WEIGHTS = (3, 1, 2)
SHARE = 1.5
MOST = 2
GOLDEN = 0.6180339887498949

BLOCK_WORDS = 128
#: Slots ranked together, rows of a source ordered together, cells that index the unit interval.
SLOT_RUN = 1 << 16
ROW_RUN = 2_000
CELLS = 1024


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def shuffle_key(doc_id: Column, text: Column, seed: str) -> Column:
    return F.md5(F.concat_ws("|", F.lit(seed), F.coalesce(doc_id.cast("string"), F.lit("")), F.md5(F.coalesce(text, F.lit("")))))


def source_targets(sized: DataFrame, weights=WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """One row per source: no, source, source_size, n, target. As long as the list of sources."""
    sources = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n"))
    sources = sources.withColumn("no", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())))
    sources = sources.withColumn("w", F.element_at(F.array(*map(F.lit, weights)), F.pmod(F.col("no") - 1, len(weights)) + 1).cast("double"))
    cap = F.col("source_size") * most
    every = Window.partitionBy()
    up = Window.orderBy("ratio", "no").rowsBetween(Window.unboundedPreceding, 0)
    sources = sources.withColumn("ratio", cap / F.col("w")).withColumn("total", F.sum("source_size").over(every) * F.lit(share))
    sources = sources.withColumn("caps", F.sum(cap).over(up)).withColumn("rest", F.sum("w").over(every) - F.sum("w").over(up))
    sources = sources.withColumn("full", F.col("caps") + F.col("ratio") * F.col("rest") <= F.col("total"))
    left = F.col("total") - F.coalesce(F.sum(F.when(F.col("full"), cap)).over(every), F.lit(0))
    open_weight = F.sum(F.when(~F.col("full"), F.col("w"))).over(every)
    return sources.withColumn("target", F.when(F.col("full"), cap.cast("double")).otherwise(F.col("w") * left / open_weight)).select("no", "source", "source_size", "n", "target")


def schedule(targets: DataFrame, slots: int, block: int = BLOCK_WORDS, most: int = MOST) -> DataFrame:
    """(slot, no, rank, pass, block) of each slot in turn; targets as from source_targets()."""
    spark = targets.sparkSession
    share = F.round(F.col("target") * 1000).cast("long")
    upto = Window.orderBy("no").rowsBetween(Window.unboundedPreceding, 0)
    bounds = targets.where("target > 0").select("no", "source_size", F.sum(share).over(upto).alias("hi"), share.alias("width"), F.sum(share).over(Window.partitionBy()).alias("whole")).withColumn("lo", F.col("hi") - F.col("width"))
    cell = lambda c: F.floor(F.col(c) * CELLS / F.col("whole"))
    # the table of cells has as many rows as there are cells and sources, whatever the documents
    cells = bounds.select("*", F.explode(F.sequence(cell("lo"), F.least(cell("hi"), F.lit(CELLS - 1)))).alias("cell"))
    points = spark.range(slots).withColumnRenamed("id", "slot").withColumn("u", F.col("slot") * F.lit(GOLDEN)).withColumn("u", F.col("u") - F.floor("u"))
    points = points.withColumn("cell", F.floor(F.col("u") * CELLS))
    dealt = points.join(F.broadcast(cells), "cell").where("u * whole >= lo and u * whole < hi").select("slot", "no", "source_size", F.expr(f"slot div {SLOT_RUN}").alias("run"))
    runs = dealt.groupBy("no", "run").agg(F.count("*").alias("k"))
    base = runs.select(F.col("no").alias("no_"), F.col("run").alias("run_"), F.coalesce(F.sum("k").over(Window.partitionBy("no").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    ranked = dealt.withColumn("r", F.row_number().over(Window.partitionBy("no", "run").orderBy("slot")) - 1)
    ranked = ranked.join(base, (F.col("no") == F.col("no_")) & (F.col("run") == F.col("run_"))).withColumn("rank", F.col("base") + F.col("r"))
    blocks = F.expr(f"(source_size + {block - 1}) div {block}")
    out = ranked.withColumn("blocks", blocks).select("slot", "no", "rank", F.expr("rank div blocks").alias("pass"), F.expr("rank % blocks").alias("block"))
    return out.where(F.col("pass") < most)


def lay_out(sized: DataFrame, rows: int) -> DataFrame:
    """Append begin: words of the same source before this row, in the seeded order of h."""
    digits = max(0, math.ceil(math.log(max(rows, 1) / ROW_RUN, 16))) if rows > ROW_RUN else 0
    runs = sized.withColumn("run", F.substring("h", 1, digits) if digits else F.lit(""))
    sums = runs.groupBy("no", "run").agg(F.sum("size").alias("k"))
    base = sums.select(F.col("no").alias("no_"), F.col("run").alias("run_"), F.coalesce(F.sum("k").over(Window.partitionBy("no").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inner = F.coalesce(F.sum("size").over(Window.partitionBy("no", "run").orderBy("h").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return runs.withColumn("inner", inner).join(base, (F.col("no") == F.col("no_")) & (F.col("run") == F.col("run_"))).withColumn("begin", F.col("base") + F.col("inner")).drop("no_", "run_", "base", "inner", "run")


def mix(docs: DataFrame, weights=WEIGHTS, share: float = SHARE, most: int = MOST, block: int = BLOCK_WORDS, seed: str = "mix") -> DataFrame:
    """(doc_id, size, source, source_size, target, taken, h) of each row; h identifies its text."""
    sized = materialise(docs.select(F.col("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size"), shuffle_key(F.col("doc_id"), F.col("text"), seed).alias("h")), "sized")
    targets = materialise(source_targets(sized, weights, share, most), "targets")
    whole = targets.agg(F.sum("target").alias("t"), F.sum("n").alias("n")).head()
    slots = math.ceil(round(whole["t"] or 0, 3) / block)
    takes = schedule(targets, slots, block, most).groupBy("no", "block").agg(F.count("*").alias("takes"))
    known = targets.select("no", F.col("source").alias("source_"), "source_size", "target")
    named = sized.join(known, F.col("source").eqNullSafe(F.col("source_"))).drop("source_")
    laid = lay_out(named, whole["n"] or 0)
    last = F.expr(f"(begin + size - 1) div {block}")
    first = F.expr(f"begin div {block}")
    pieces = laid.withColumn("block", F.explode_outer(F.when(F.col("size") > 0, F.sequence(first, last))))
    words = F.least(F.col("begin") + F.col("size"), (F.col("block") + 1) * block) - F.greatest(F.col("begin"), F.col("block") * block)
    taken = pieces.join(takes.select(F.col("no").alias("no_t"), F.col("block").alias("block_t"), "takes"), (F.col("no") == F.col("no_t")) & (F.col("block") == F.col("block_t")), "left")
    # rows without words share a begin: their number tells equal ones apart
    per_row = taken.withColumn("words", F.coalesce(words * F.col("takes"), F.lit(0)))
    with_words = per_row.where("size > 0").groupBy("no", "begin", "doc_id", "size", "source", "source_size", "target", "h").agg(F.sum("words").alias("taken"))
    columns = ["doc_id", "size", "source", "source_size", "target", "taken", "h"]
    return with_words.select(columns).unionByName(laid.where("size = 0").withColumn("taken", F.lit(0).cast("long")).select(columns))


def repeat_documents(docs: DataFrame, **options) -> DataFrame:
    """The mix as rows: each document as often as its taken words fill it, a part counting as a whole.

    A document that a source's last pass cuts is kept whole, one per source at most besides the
    last short block. Rows equal in doc_id, text and source are indistinguishable and repeated together.
    """
    seed = options.get("seed", "mix")
    times = mix(docs, **options).where("taken > 0").groupBy("h", "source").agg(F.sum(F.ceil(F.col("taken") / F.col("size"))).cast("int").alias("_times"))
    times = times.select(F.col("h").alias("_h2"), F.col("source").alias("_source2"), "_times")
    packed, unpack = carry(docs, ["doc_id", "text", "source"])
    keyed = packed.withColumn("_h", shuffle_key(F.col("doc_id"), F.col("text"), seed)).withColumn("_source", F.col("source").cast("string"))
    single = keyed.dropDuplicates(["_h", "_source"])
    joined = single.join(times, (F.col("_h") == F.col("_h2")) & F.col("_source").eqNullSafe(F.col("_source2")))
    return unpack(joined.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))))
