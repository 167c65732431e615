"""Quality selection by importance resampling with hashed n-gram models.

Two bags of hashed words and word pairs are fitted: one on target rows (labelled good), one
on all raw rows. A text's importance is the log ratio of the two multinomial models summed
over its n-grams. Adding independent Gumbel noise to the importances and keeping the largest k
draws k rows without replacement in proportion to their importance. The noise comes from a
hash of the id, so reruns agree; ranks come from a range-partitioned sort of narrow rows.

Edge cases: null texts and texts without words have log importance 0; a table without target
rows has importance 0 everywhere; repeated rows share their noise, and a tie at the cut is
broken by id and then text, so exactly k rows stay; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from repsum.llm.arrow import add_columns, slices
from repsum.plans.ranks import positions
from repsum.plans.scratch import materialise

BUCKETS = 10_000
SMOOTHING = 1.0
#: Good rows that the target model is fitted on at most, by smallest hash of the id: their ids, 16 MB, go to every task.
TARGET_ROWS = 2_000_000
#: Log importances are divided by it before the draw; 1 draws by the ratio of the models itself.
TEMPERATURE = 1.0

_TABLE = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def grams(text: str | None, buckets: int = BUCKETS) -> np.ndarray:
    """Bucket of each word and each pair of neighbouring words of the whole text.

    Words are lower-cased runs between white space, punctuation included, since layout junk
    shows there.
    """
    words = (text or "").encode("utf-8", "surrogatepass").translate(_TABLE).split()
    if not words:
        return np.empty(0, np.int64)
    one = np.fromiter(map(zlib.crc32, words), np.uint64, len(words))
    two = (one[:-1] * np.uint64(0x9E3779B1) + one[1:]) ^ np.uint64(0x5BD1E995)
    mixed = np.concatenate([one, two]) * np.uint64(0x9E3779B97F4A7C15)
    return ((mixed >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)


def count_grams(docs: DataFrame, buckets: int = BUCKETS, text_col: str = "text", target_col: str = "is_target") -> np.ndarray:
    """(2, buckets) counts: of target rows, of all rows. Each task sends one row per bucket at most."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((2, buckets), np.int64)
        for whole in batches:
            for part in slices(whole, text_col):
                for text, good in zip(part.column(text_col).to_pylist(), part.column(target_col).to_pylist()):
                    c = np.bincount(grams(text, buckets), minlength=buckets)
                    counts[1] += c
                    if good:
                        counts[0] += c
        seen = np.flatnonzero(counts[1])
        yield pa.RecordBatch.from_arrays([pa.array(seen), pa.array(counts[0][seen]), pa.array(counts[1][seen])], names=["bucket", "target", "raw"])

    sums = docs.select(text_col, target_col).mapInArrow(run, "bucket long, target long, raw long").groupBy("bucket").agg(F.sum("target").alias("target"), F.sum("raw").alias("raw"))
    out = np.zeros((2, buckets), np.int64)
    for r in sums.collect():  # one row per bucket
        out[:, r["bucket"]] = r["target"], r["raw"]
    return out


def log_ratio(counts: np.ndarray, smoothing: float = SMOOTHING) -> np.ndarray:
    if not counts[0].any():
        return np.zeros(counts.shape[1])
    p = (counts + smoothing) / (counts.sum(axis=1, keepdims=True) + smoothing * counts.shape[1])
    return np.log(p[0]) - np.log(p[1])


def add_importance(docs: DataFrame, ratio: np.ndarray, text_col: str = "text") -> DataFrame:
    """Append log_importance, the sum of the models' log ratio over a text's n-grams."""

    def work():
        def one(text: str | None) -> float:
            at = grams(text, len(ratio))
            return float(ratio[at].sum())

        return lambda texts: {"log_importance": [one(t) for t in texts]}

    return add_columns(docs, text_col, [T.StructField("log_importance", T.DoubleType())], work)


def gumbel(key: Column, seed: int | Column) -> Column:
    """Standard Gumbel noise of a row, the same whenever it is asked for."""
    uniform = (F.pmod(F.xxhash64(key, F.lit(seed).cast("int")), F.lit(1 << 40)) + F.lit(0.5)) / F.lit(float(1 << 40))
    return -F.log(-F.log(uniform))


def importances(docs: DataFrame, target: DataFrame, temperature: float = TEMPERATURE, seed: int = 7, target_rows: int = TARGET_ROWS) -> DataFrame:
    """(doc_id, text_hash, log_importance, key) of every row; ``target`` holds the doc_ids of good rows.

    The target model is fitted on at most ``target_rows`` good rows, so their ids can be sent to
    every task and no text is shuffled; the raw model counts all rows.
    """
    rows = docs.select("doc_id", "text")
    marks = target.select(F.col("doc_id").alias("good_id")).distinct().orderBy(F.xxhash64("good_id"), "good_id").limit(target_rows)
    marked = rows.join(F.broadcast(marks), rows["doc_id"] == marks["good_id"], "left").select("doc_id", "text", F.col("good_id").isNotNull().alias("is_target"))
    ratio = log_ratio(count_grams(marked))
    scored = add_importance(rows, ratio).select("doc_id", F.xxhash64("text").alias("text_hash"), "log_importance")
    return scored.withColumn("key", F.col("log_importance") / F.lit(temperature) + gumbel(F.col("doc_id"), seed))


def resample(docs: DataFrame, target: DataFrame, share: float, temperature: float = TEMPERATURE, seed: int = 7) -> DataFrame:
    """(doc_id, log_importance, key, rank, selected): rank counts from 0; the first ceil(share * rows) are drawn."""
    scored = materialise(importances(docs, target, temperature, seed), "importances")
    ranked = positions(scored.withColumn("_g", F.lit(0)).withColumn("_down", -F.col("key")), ["_g"], ["_down", "doc_id", "text_hash"], "rank")
    ranked = materialise(ranked.select("doc_id", "log_importance", "key", "rank"), "ranked")
    k = F.lit(int(np.ceil(share * ranked.count())))
    return ranked.withColumn("selected", F.col("rank") < k)
