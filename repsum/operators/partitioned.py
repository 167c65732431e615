"""Greedy in parallel: local summaries of parts, then greedy over their union."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from repsum.operators.blocks import Blocks, Entries
from repsum.operators.greedy import GAMMA, PASS_POOL, Pick, Result, _as_pick, _best_of_parts, compress, lazy, value
from repsum.plans.scratch import materialise


def part_of(parts: int, seed: int = 42) -> Column:
    """Part of an entry by a hash of its id that every SQL engine can compute."""
    digest = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("qid").cast("string")))
    return F.pmod(F.conv(F.substring(digest, 1, 8), 16, 10).cast("long"), F.lit(parts)).cast("int")


#: Entries and tokens of a part that one task holds in memory; larger parts are picked from by passes, with the same picks.
PART_ENTRIES, PART_TOKENS = 200_000, 4_000_000


def _local(picks: list[Pick] | Entries, d: np.ndarray, budget: float, unit: bool, gamma) -> Result:
    """Lazy greedy over entries in memory."""
    m, result = np.zeros(len(d)), Result()
    lazy(picks, d, m, float(budget), int(budget) if unit else None, gamma, None, result)
    return result


def local_summaries(vectors: DataFrame | Blocks, d: np.ndarray, budget: float, parts: int, gamma=GAMMA, unit: bool = True, part: Column | None = None, scope: str = "global") -> DataFrame:
    """(part, pick_no, qid, cost, gain, tids, mults) of each part's own greedy run.

    Parts of up to ``PART_ENTRIES`` entries and ``PART_TOKENS`` tokens are run in the memory of one task
    each; larger ones are picked from by passes that serve all of them, with the same picks. ``scope``
    'local' replaces the target by the part's own shares.
    """
    spark = vectors.sparkSession
    shared = spark.sparkContext.broadcast(d)
    schema = "part int, pick_no int, qid long, cost double, gain double, tids array<int>, mults array<int>"

    def run(key: tuple, table: pa.Table) -> pa.Table:
        entries, own = Entries.of_table(table), shared.value
        if scope == "local":
            own = np.bincount(entries.tids, weights=entries.mults, minlength=len(own))
            own = own / max(own.sum(), 1)
        got = _local(entries, own, budget, unit, gamma).picks
        return pa.table({"part": pa.array([key[0].as_py()] * len(got), pa.int32()), "pick_no": pa.array(range(1, len(got) + 1), pa.int32()), "qid": pa.array([p.qid for p in got], pa.int64()), "cost": pa.array([p.cost for p in got], pa.float64()), "gain": pa.array([p.gain for p in got], pa.float64()), "tids": pa.array([p.tids.tolist() for p in got], pa.list_(pa.int32())), "mults": pa.array([p.mults.tolist() for p in got], pa.list_(pa.int32()))})

    blocks, vectors = (vectors, vectors.rows()) if isinstance(vectors, Blocks) else (None, vectors)
    dealt = vectors.withColumn("part", part_of(parts) if part is None else part)
    counted = blocks.counts(parts) if blocks is not None and part is None else dealt.groupBy("part").agg(F.count("*").alias("n"), F.sum(F.size("tids")).alias("t"))
    sizes = {r["part"]: (r["n"], r["t"] or 0) for r in counted.collect()}  # a row per part
    large = sorted(k for k, (n, t) in sizes.items() if n > PART_ENTRIES or t > PART_TOKENS)
    if not large:
        return dealt.groupBy("part").applyInArrow(run, schema)
    out = dealt.where(~F.col("part").isin(large)).groupBy("part").applyInArrow(run, schema)
    if part is None:
        found = _by_passes(blocks or Blocks.of(vectors), d, budget, parts, large, gamma, unit, scope)
        rows = [(k, n, p.qid, p.cost, p.gain, p.tids.tolist(), p.mults.tolist()) for k in large for n, p in enumerate(found[k].picks, 1)]
        few = spark.createDataFrame(rows, schema)
        return few if len(large) == len(sizes) else out.unionByName(few)
    rows = []
    for k in large:
        own = materialise(dealt.where(F.col("part") == k).drop("part"), "part")
        target = _shares(own, len(d)) if scope == "local" else d
        rows += [(k, n, p.qid, p.cost, p.gain, p.tids.tolist(), p.mults.tolist()) for n, p in enumerate(compress(own, target, budget, gamma, unit=unit, safeguard=False).picks, 1)]
    return out.unionByName(spark.createDataFrame(rows, schema))


def _by_passes(blocks: Blocks, d: np.ndarray, budget: float, parts: int, some: list[int], gamma, unit: bool, scope: str) -> dict[int, Result]:
    """Greedy over each of ``some`` parts; a pass scores all that have not ended and brings the best of each to the driver, as in compress()."""
    blocks = blocks.hashed()
    targets = np.tile(d, (parts, 1))
    if scope == "local":
        counted = blocks.counts(parts, len(d)).toArrow()
        targets = np.zeros((parts, len(d)))
        targets[counted.column("part").to_numpy(), counted.column("tid").to_numpy()] = counted.column("n").to_numpy()
        targets /= np.maximum(targets.sum(axis=1, keepdims=True), 1)
    m, left, results = np.zeros((parts, len(d))), np.full(parts, -np.inf), {k: Result() for k in some}
    left[some] = budget
    open_, count, alone, tasks = set(some), int(budget) if unit else None, False, blocks.table.rdd.getNumPartitions()
    while open_:
        want = max(1, PASS_POOL // (2 * len(open_)))
        found = _best_of_parts(blocks, targets, m, left, [q for r in results.values() for q in r.ids()], gamma, 1 if alone else want, tasks, alone)
        slow = False
        for k in list(open_):
            own, (inside, keys, fence) = results[k], found.get(k, (None, None, None))
            before = len(own.picks)
            if inside is not None and len(inside):
                own.passes += 1
                left[k] = lazy(inside, targets[k], m[k], left[k], before + 1 if alone else count, gamma, None if alone else fence, own, keys)
            if inside is None or not len(inside) or fence is None and not alone or count is not None and len(own.picks) >= count:
                open_.remove(k)
                left[k] = -np.inf
            slow |= len(own.picks) == before
        alone = slow and not alone  # a bound beats every key of a part: each part's next pick is made by keys
    return results


def _shares(vectors: DataFrame, size: int) -> np.ndarray:
    """The entries' own target by tid; a row for each tid of a checked domain."""
    pairs = vectors.select(F.explode(F.arrays_zip("tids", "mults")).alias("x")).groupBy("x.tids").agg(F.sum("x.mults").alias("n")).toArrow()
    own = np.zeros(size)
    own[pairs.column("tids").to_numpy()] = pairs.column("n").to_numpy()
    return own / max(own.sum(), 1)


def merge(local: DataFrame, d: np.ndarray, budget: float, gamma=GAMMA, unit: bool = True) -> Result:
    """Greedy over the union of local summaries, or the best single part if that is worth more."""
    rows = local.orderBy("part", "pick_no").collect()  # at most parts times the budget
    merged = _local([_as_pick(r) for r in rows], d, budget, unit, gamma)
    by_part: dict[int, list[Pick]] = {}
    for r in rows:
        by_part.setdefault(r["part"], []).append(_as_pick(r))
    best = max(by_part.values(), key=lambda p: value(d, p, gamma), default=[])
    if best and value(d, best, gamma) > value(d, merged.picks, gamma):
        merged.picks, merged.winner = best, "part"
    return merged


def compress_partitioned(vectors: DataFrame | Blocks, d: np.ndarray, budget: float, parts: int | str, gamma=GAMMA, unit: bool = True, levels: int = 1, fan: int = 8, scope: str = "global") -> Result:
    """Two rounds, or a tree of merges with ``levels`` above 1. ``parts`` 'budget' takes as many parts as picks."""
    n = int(budget) if parts == "budget" else int(parts)
    local = materialise(local_summaries(vectors, d, budget, n, gamma, unit, scope=scope), "local")
    for _ in range(levels - 1):
        n = max(1, n // fan)
        local = materialise(local_summaries(local.select("qid", "cost", "tids", "mults"), d, budget, n, gamma, unit, scope="global"), "local")
    return merge(local, d, budget, gamma, unit)
