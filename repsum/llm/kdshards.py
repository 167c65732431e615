"""K-d tree sharding at distributed weighted medians.

Documents with equal texts form a group that stays in one shard. A group has the metadata
coordinates length, source and language, each scaled to the unit interval of its possible
range, and a weight: its bytes, or its rows. The tree splits each node along the dimension in
which its groups spread widest, at the weighted quantile that matches the room of the shards
on either side (the median, while they are all empty). Ties along a dimension are broken by a
hash of the text, so a split can fall inside a crowded value. Quantiles come from histograms of
fixed size that are refined around the crossing bin; nothing of the data is collected.

Groups above ``LARGE`` of a shard are placed before the tree is grown, largest first, each into the
shard with most room: at most shards / LARGE of them exist, whatever the input. Only a group that
exceeds the room of every shard is spread over several shards, by rank, because equal loads are
the law.

Edge cases: null text counts as empty (size 1); null source or language have coordinate zero;
repeated rows are one group and keep a slot each; an empty table yields an empty result; other
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from repsum.plans.ranks import positions
from repsum.plans.scratch import materialise

SHARDS = 16
LARGE = 0.01
BINS = 2048
#: A quantile is refined until the crossing bin holds less than this share of a shard.
FINE = 0.001

_SCALE = 1 << 20
_TIE = 1 << 31
DIMENSIONS = ("length", "origin", "tongue")


def sized_rows(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(
        F.col("doc_id"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.xxhash64(text).alias("text_hash"),
        F.coalesce(F.crc32(F.col("source").cast("string").cast("binary")) % _SCALE, F.lit(0)).alias("origin"),
        F.coalesce(F.crc32(F.col("lang").cast("string").cast("binary")) % _SCALE, F.lit(0)).alias("tongue"),
    )


def groups_of(rows: DataFrame, law: str) -> DataFrame:
    weight = F.sum("size") if law == "bytes" else F.count("*")
    grouped = rows.groupBy("text_hash", "size", "text_crc32").agg(weight.alias("weight"), F.count("*").alias("n"), F.min("origin").alias("origin"), F.min("tongue").alias("tongue"))
    return grouped.withColumn("length", F.least(F.lit(_SCALE - 1), F.floor(F.log2(F.col("size").cast("double")) / 31 * _SCALE)).cast("long")).withColumn("tie", F.pmod(F.col("text_hash"), F.lit(_TIE)))


def _key(dimension: str) -> Column:
    return F.col(dimension) * F.lit(_TIE) + F.col("tie")


def place_large(large: list[tuple], room: list[float]) -> tuple[dict, dict]:
    """({group: shard}, {group: [(share, shard), ...]}) for groups given largest first; fills ``room``."""
    whole, spread = {}, {}
    for key, weight in large:
        best = max(range(len(room)), key=lambda s: (room[s], -s))
        if weight <= room[best]:
            whole[key] = best
            room[best] -= weight
            continue
        rest, parts = weight, []
        while rest > 1e-9:
            best = max(range(len(room)), key=lambda s: (room[s], -s))
            put = min(rest, room[best]) if room[best] > 0 else rest
            parts.append((put / weight, best))
            room[best] -= put
            rest -= put
        spread[key] = parts
    return whole, spread


def grow_tree(groups: DataFrame, room: list[float], fine: float) -> DataFrame:
    """Append the shard of each group; one histogram job per refinement and level."""
    nodes: dict[int, tuple[int, int]] = {0: (0, len(room))}
    tree: dict[int, tuple[str, int]] = {}  # node: dimension and cut; children of k are 2k + 1 and 2k + 2

    def walk(k: int, leaf) -> Column:
        if k not in tree:
            return F.lit(leaf(k))
        dim, cut = tree[k]
        return F.when(_key(dim) < cut, walk(2 * k + 1, leaf)).otherwise(walk(2 * k + 2, leaf))

    while any(b - a > 1 for a, b in nodes.values()):
        split = {k: v for k, v in nodes.items() if v[1] - v[0] > 1}
        at = groups.withColumn("node", walk(0, lambda k: k)).where(F.col("node").isin(list(split)))
        spans = {r["node"]: r for r in at.groupBy("node").agg(F.sum("weight").alias("w"), *(f(d).alias(f"{d}_{n}") for d in DIMENSIONS for n, f in (("lo", F.min), ("hi", F.max)))).collect()}
        cuts: dict[int, list] = {}
        for k, (a, b) in split.items():
            middle = (a + b) // 2
            left, right = sum(max(0.0, x) for x in room[a:middle]), sum(max(0.0, x) for x in room[middle:b])
            if k not in spans:
                cuts[k] = [DIMENSIONS[0], 0, 1, 0.0, 0.0, middle]
                continue
            r = spans[k]
            dim = max(DIMENSIONS, key=lambda d: r[f"{d}_hi"] - r[f"{d}_lo"])  # the first of the widest
            goal = r["w"] * (left / (left + right) if left + right > 0 else 0.5)
            cuts[k] = [dim, r[f"{dim}_lo"] * _TIE, (r[f"{dim}_hi"] + 1) * _TIE, 0.0, goal, middle]
        busy = {k for k in split if k in spans}
        while busy:
            key, low, step = (F.lit(None).cast("long") for _ in range(3))
            for k in busy:
                dim, lo, hi, *_ = cuts[k]
                width = -(-(hi - lo) // BINS)
                here = F.col("node") == k
                key, low, step = F.when(here, _key(dim)).otherwise(key), F.when(here, F.lit(lo)).otherwise(low), F.when(here, F.lit(width)).otherwise(step)
            table = at.where(F.col("node").isin(list(busy))).select("node", "weight", key.alias("key"), low.alias("low"), step.alias("step"))
            table = table.withColumn("bin", F.expr("(key - low) div step")).where((F.col("key") >= F.col("low")) & (F.col("bin") < BINS))
            found: dict[int, list] = {}
            for r in table.groupBy("node", "bin").agg(F.sum("weight").alias("w")).collect():  # nodes x bins rows at most
                found.setdefault(r["node"], []).append((r["bin"], r["w"]))
            for k in list(busy):
                dim, lo, hi, below, goal, middle = cuts[k]
                width = -(-(hi - lo) // BINS)
                crossing = None
                for n, w in sorted(found.get(k, [])):
                    if (n + 1) * width + lo > hi and n * width + lo >= hi:
                        break
                    if below + w >= goal:
                        crossing = (n, w)
                        break
                    below += w
                if crossing is None:
                    cuts[k] = [dim, hi, hi, below, goal, middle]
                    busy.discard(k)
                    continue
                n, w = crossing
                new_lo, new_hi = lo + n * width, min(hi, lo + (n + 1) * width)
                if width == 1 or w <= fine:
                    cut = new_hi if goal - below > w / 2 else new_lo
                    cuts[k] = [dim, cut, cut, below, goal, middle]
                    busy.discard(k)
                else:
                    cuts[k] = [dim, new_lo, new_hi, below, goal, middle]
        following: dict[int, tuple[int, int]] = {k: v for k, v in nodes.items() if k not in split}
        for k, (a, b) in split.items():
            dim, cut, *_, middle = cuts[k]
            tree[k] = dim, cut
            following[2 * k + 1], following[2 * k + 2] = (a, middle), (middle, b)
        nodes = following
    return groups.withColumn("shard", walk(0, lambda k: nodes[k][0]).cast("int"))


def shard_documents(docs: DataFrame, shards: int = SHARDS, law: str = "bytes") -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot) of every row; law: ``bytes`` or ``rows``."""
    if law not in ("bytes", "rows"):
        raise ValueError(f"law {law!r} is not one a k-d tree can hold")
    rows = materialise(sized_rows(docs), "sized-rows")
    groups = materialise(groups_of(rows, law), "text-groups")
    total = groups.agg(F.sum("weight")).head()[0] or 0
    share = total / shards
    room = [share] * shards
    limit = LARGE * share
    listed = groups.where(F.col("weight") > limit).select("text_hash", "size", "text_crc32", "weight", "n").collect()  # at most shards / LARGE
    large = sorted((((r["text_hash"], r["size"], r["text_crc32"]), float(r["weight"])) for r in listed), key=lambda x: (-x[1], x[0]))
    whole, spread = place_large(large, room)
    small = grow_tree(groups.where(F.col("weight") <= limit), room, FINE * share)
    spark = docs.sparkSession
    ranges = [(*k, s, 0.0, 1.0) for k, s in whole.items()]
    for k, parts in spread.items():
        low = 0.0
        for i, (part, s) in enumerate(parts):
            high = 1.0 if i == len(parts) - 1 else low + part
            ranges.append((*k, s, low, high))
            low = high
    schema = "text_hash long, size long, text_crc32 long, shard int, low double, high double"
    fixed = spark.createDataFrame(ranges, schema)
    every = small.select("text_hash", "size", "text_crc32", "shard", F.lit(0.0).alias("low"), F.lit(1.0).alias("high")).unionByName(fixed)
    key = ["text_hash", "size", "text_crc32"]
    at = rows.withColumn("at", F.lit(0.5))
    if spread:  # the rows of a spread group are dealt by their rank in it
        count = {(r["text_hash"], r["size"], r["text_crc32"]): r["n"] for r in listed}
        large_keys = F.broadcast(spark.createDataFrame([(*k, count[k]) for k in spread], "text_hash long, size long, text_crc32 long, n long"))  # fewer than shards
        ranked = positions(rows.join(large_keys, key), key, ["doc_id"], "rank")
        at = at.join(large_keys, key, "left_anti").unionByName(ranked.withColumn("at", (F.col("rank") + 0.5) / F.col("n")).drop("rank", "n"))
    put = at.join(every, key).where("at >= low and at < high").select("doc_id", "size", "text_crc32", "shard")
    return positions(put, ["shard"], ["doc_id", "text_crc32", "size"], "slot")
