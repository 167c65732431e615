"""From a log to what the compressor works on, written once and reused."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame, functions as F

from repsum.operators import encode
from repsum.operators.blocks import Blocks
from repsum.operators.features import BUCKETS, SMALL_DOMAIN, Log, domain, numbered, pack, query_sizes, tokens
from repsum.operators.greedy import target_array
from repsum.plans.scratch import materialise


@dataclass
class Prepared:
    log: Log
    domain: DataFrame
    vectors: DataFrame
    d: np.ndarray
    made: DataFrame | None = None  # tokens, if they were written on the way
    packed: Blocks | None = None

    @cached_property
    def tokens(self) -> DataFrame:
        """(qid, feature, token, mult) of the whole log, written when first asked for; of vectors in blocks if that is what there is."""
        if self.made is not None:
            return self.made
        each = self.vectors.select("qid", F.explode(F.arrays_zip("tids", "mults")).alias("x")).select("qid", F.col("x.tids").alias("tid"), F.col("x.mults").cast("long").alias("mult"))
        return materialise(each.join(F.broadcast(self.domain.select("tid", "feature", "token")), "tid").select("qid", "feature", "token", "mult"), "tokens")

    @cached_property
    def blocks(self) -> Blocks:
        """The vectors in blocks, written once: what passes read fastest."""
        return self.packed or Blocks.of(self.vectors)

    def kinds(self) -> list[str]:
        """The features that have tokens, in order; a few, whatever the log."""
        return [r["feature"] for r in self.domain.select("feature").distinct().orderBy("feature").collect()]

    def features(self) -> np.ndarray:
        """Number of each tid's feature among kinds(); tokens themselves stay where they are."""
        names = F.array(*map(F.lit, self.kinds() or [""]))
        got = self.domain.select("tid", F.array_position(names, F.col("feature")).cast("int").alias("k")).toPandas()
        return got.sort_values("tid")["k"].to_numpy(dtype=int) - 1

    def of(self, qids: list[int] | DataFrame) -> DataFrame:
        """Tokens of some entries; a list is a summary and therefore small, a table is sent around only if the session's limit allows."""
        if isinstance(qids, DataFrame):
            return self.tokens.join(qids.select("qid"), "qid", "left_semi")
        return self.tokens.where(F.col("qid").isin(qids))


def prepare(log: Log, buckets: int = BUCKETS, pinned=None, target: DataFrame | None = None, weights: DataFrame | None = None, size_cost: bool = False, cost: str | None = None) -> Prepared:
    """``cost`` names a numeric feature of a log with rows; entries without it cost no number and are never picked."""
    if log.rows is not None and not size_cost:
        made = encode.coded(log.rows, cost)
        bounds = encode.edges(made, pinned)
        dom = materialise(numbered(encode.frequencies(made, bounds, buckets)), "domain")
        if dom.limit(SMALL_DOMAIN + 1).count() <= SMALL_DOMAIN:
            blocks = encode.packed(made, dom, bounds, buckets)
            return Prepared(log, dom, blocks.rows(), target_array(dom, target, weights), packed=blocks)
    toks = materialise(tokens(log, buckets, pinned), "tokens")
    dom = materialise(domain(toks), "domain")
    costs = query_sizes(toks).select("qid", F.col("size").alias("cost")) if size_cost else None
    if cost is not None:
        costs = log.entries.select("qid", F.col(cost).alias("cost"))
    vectors = materialise(pack(toks, dom, costs), "vectors")
    return Prepared(log, dom, vectors, target_array(dom, target, weights), toks)


def views(log: Log, name: str, buckets: int = BUCKETS) -> None:
    """Temporary views of a log for SQL: ``name``_entries, ``name``_tokens and ``name``_domain."""
    toks = tokens(log, buckets)
    for kind, table in (("entries", log.entries), ("tokens", toks), ("domain", domain(toks))):
        table.createOrReplaceTempView(f"{name}_{kind}")


def sqrt_budget(entries: DataFrame) -> int:
    return math.isqrt(entries.count())
