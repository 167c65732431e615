"""What the compressor is compared with: sampling, clustering, pure coverage, frequency."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from repsum.functions.distance import euclid, jaccard, mixed, pairwise
from repsum.plans.scratch import materialise

#: Entries whose distances the divisive method holds at once, as a matrix.
MAX_PAIRWISE = 10_000
#: Entries of a cluster in one piece; all pairs of pieces are compared, each pair in one task's memory.
PIECE = 2048
#: What the distance of a pair loses in blocks at most, as a share of the cluster's largest one.
BLOCK_LOSS = 1e-7


def hash_order(seed: int | str = 42) -> Column:
    """A seeded order of entries that every SQL engine can reproduce."""
    return F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("qid").cast("string")))


def random_sample(entries: DataFrame, k: int, seed: int | str = 42) -> DataFrame:
    """(pick_no, qid): k entries by seeded hash; a partial sort, never a full one."""
    top = entries.select("qid", hash_order(seed).alias("h")).orderBy("h", "qid").limit(k)
    return top.select(F.row_number().over(Window.orderBy("h", "qid")).alias("pick_no"), "qid")


def sample_knapsack(entries: DataFrame, budget: float, seed: int | str = 42) -> DataFrame:
    """(pick_no, qid, cost): the longest prefix of the hash order whose costs fit the budget.

    A sort of the first rows only, as many as the average cost lets expect, doubled until they
    pass the budget; the running sum is over them. Null costs count nothing.
    """
    priced = entries.select("qid", F.coalesce("cost", F.lit(0)).alias("cost"), hash_order(seed).alias("h"))
    rows, total = priced.agg(F.count("*"), F.sum("cost")).head()
    most = min(rows, int(2 * budget * rows / total) + 16) if total else rows
    while True:
        top = priced.orderBy("h", "qid").limit(most)
        if most >= rows or top.agg(F.sum("cost")).head()[0] > budget:
            break
        most = min(rows, 2 * most)
    w = Window.orderBy("h", "qid")
    run = top.select("qid", "cost", F.row_number().over(w).alias("pick_no"), F.sum("cost").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("spent"))
    return run.where(F.col("spent") <= budget).select("pick_no", "qid", "cost")


def top_frequency(vectors: DataFrame, k: int) -> DataFrame:
    """(pick_no, qid, n): the smallest id of each of the k most frequent identical entries."""
    same = vectors.groupBy("tids", "mults").agg(F.min("qid").alias("qid"), F.count("*").alias("n"))
    top = same.select("qid", "n").orderBy(F.desc("n"), "qid").limit(k)
    return top.select(F.row_number().over(Window.orderBy(F.desc("n"), "qid")).alias("pick_no"), "qid", "n")


def max_cover(vectors: DataFrame, size: int, k: int) -> list[int]:
    """Greedy maximum coverage: each pick adds most tokens not seen so far."""
    from repsum.operators.greedy import compress

    return compress(vectors, np.full(size, 1.0), k, "cover").ids()


def distances_to(points: DataFrame, chosen: DataFrame, kind: str = "numeric") -> DataFrame:
    """(qid, other, dist): every entry against each of a few chosen ones, itself included; k rows an entry, nothing shuffled."""
    columns = [c for c in ("num", "toks") if c in chosen.columns]
    few = F.broadcast(chosen.select(F.col("qid").alias("other"), *(F.col(c).alias(f"o_{c}") for c in columns)))
    pair = {"numeric": lambda: euclid(F.col("num"), F.col("o_num")), "categorical": lambda: jaccard(F.col("toks"), F.col("o_toks")), "mixed": lambda: mixed(F.col("num"), F.col("o_num"), F.col("toks"), F.col("o_toks"))}
    return points.crossJoin(few).select("qid", "other", pair[kind]().alias("dist"))


def medoid_assign(points: DataFrame, medoids: DataFrame, kind: str = "numeric") -> DataFrame:
    """(qid, medoid, dist): nearest medoid of every entry, ties to the smaller id.

    Medoids are k rows of a fixed k; the minimum is taken within the row, so nothing is shuffled.
    """
    held = medoids.select(F.struct(F.col("qid").alias("m"), *(F.col(c).alias(f"m_{c}") for c in ("num", "toks") if c in medoids.columns)).alias("s")).agg(F.collect_list("s").alias("all"))
    wide = points.crossJoin(F.broadcast(held))

    def dist(s: Column) -> Column:
        if kind == "numeric":
            return euclid(F.col("num"), s["m_num"])
        if kind == "categorical":
            return jaccard(F.col("toks"), s["m_toks"])
        return mixed(F.col("num"), s["m_num"], F.col("toks"), s["m_toks"])

    near = F.array_min(F.transform("all", lambda s: F.struct(F.round(dist(s), 9).alias("dist"), s["m"].alias("m"))))
    return wide.select("qid", near.alias("n")).select("qid", F.col("n.m").alias("medoid"), F.col("n.dist").alias("dist"))


def _pair_distances(a: pa.Table, b: pa.Table, kind: str) -> np.ndarray:
    """All distances of two pieces: numbers by products of matrices, sets by products of their incidence matrices."""
    parts = []
    if kind != "categorical":
        x, y = (t.column("num").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(t.num_rows, -1) for t in (a, b))
        middle = x.mean(axis=0) if x.size else 0.0
        x, y = x - middle, y - middle
        if x.shape[1] <= 8:
            square = sum((x[:, d, None] - y[None, :, d]) ** 2 for d in range(x.shape[1])) if x.shape[1] else np.zeros((len(x), len(y)))
        else:
            square = (x**2).sum(1)[:, None] + (y**2).sum(1)[None, :] - 2 * (x @ y.T)
        parts.append(np.sqrt(np.maximum(square, 0.0) / max(1, x.shape[1])))
    if kind != "numeric":
        sets = [[set(v) for v in t.column("toks").to_pylist()] for t in (a, b)]
        kinds = [{k: n for n, k in enumerate(dict.fromkeys(map(frozenset, own)))} for own in sets]  # few different sets, met by many
        names = {t: n for n, t in enumerate(sorted(set().union(*kinds[0], *kinds[1])))}
        tables = []
        for own in kinds:
            table = np.zeros((len(own), len(names)), np.float32)
            for k, n in own.items():
                table[n, [names[t] for t in k]] = 1
            tables.append(table)
        both = (tables[0] @ tables[1].T).astype(np.float64)
        either = tables[0].sum(1, dtype=np.float64)[:, None] + tables[1].sum(1, dtype=np.float64)[None, :] - both
        gap = np.where(either > 0, 1 - both / np.where(either > 0, either, 1), 0.0)
        at = [np.array([k[frozenset(v)] for v in own], int) for own, k in zip(sets, kinds)]
        parts.append(gap[at[0][:, None], at[1][None, :]])
    return sum(parts) / len(parts)


def pair_statistics(points: DataFrame, assigned: DataFrame, kind: str = "numeric", piece: int | None = None) -> DataFrame:
    """(medoid, qid, total, far, other): each entry's summed distance to its cluster, its largest one and to whom (the smallest such id).

    Quadratic in cluster size, as the methods are, but in pieces: a cluster's entries are dealt into
    pieces of about ``PIECE``, each task compares two of them as matrices and hands over a row per entry,
    so memory does not grow with the cluster. Sums are right but for ``BLOCK_LOSS`` of the largest distance a pair.
    """
    columns = [c for c in ("num", "toks") if c in points.columns]
    own = materialise(points.join(assigned.select(F.col("qid").alias("_q"), "medoid"), F.col("qid") == F.col("_q")).select("medoid", "qid", *columns), "clusters")
    size = own.groupBy("medoid").agg(F.count("*").alias("n")).withColumn("pieces", F.ceil(F.col("n") / F.lit(piece or PIECE)).cast("int"))  # a row per cluster
    dealt = own.join(F.broadcast(size.select("medoid", "pieces")), "medoid").withColumn("at", F.pmod(F.xxhash64("qid"), F.col("pieces")).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.col("pieces") - 1)).alias("p")
    spread = dealt.select("medoid", "qid", *columns, "at", every)
    pairs = spread.withColumns({"i": F.least("at", "p"), "j": F.greatest("at", "p")}).drop("p", "pieces")

    def run(key: tuple, table: pa.Table) -> pa.Table:
        medoid, i, j = (k.as_py() for k in key)
        table = table.sort_by("qid")
        at = table.column("at").to_numpy()
        a, b = table.filter(pa.array(at == i)), table.filter(pa.array(at == j))
        out = []
        for x, y in ((a, b),) if i == j else ((a, b), (b, a)):
            if not x.num_rows or not y.num_rows:
                continue
            ids, others, total, far, other = x.column("qid").to_numpy(), y.column("qid").to_numpy(), [], [], []
            for begin in range(0, len(ids), 512):
                d = _pair_distances(x.slice(begin, 512), y, kind)
                most = np.argmax(d, axis=1)
                total.append(d.sum(axis=1)), far.append(d.max(axis=1)), other.append(others[most])
            out.append(pa.table({"medoid": pa.array([medoid] * len(ids), pa.int64()), "qid": pa.array(ids, pa.int64()), "total": np.concatenate(total), "far": np.concatenate(far), "other": pa.array(np.concatenate(other), pa.int64())}))
        empty = pa.schema([("medoid", pa.int64()), ("qid", pa.int64()), ("total", pa.float64()), ("far", pa.float64()), ("other", pa.int64())]).empty_table()
        return pa.concat_tables(out) if out else empty

    part = pairs.groupBy("medoid", "i", "j").applyInArrow(run, "medoid long, qid long, total double, far double, other long")
    widest = F.max(F.struct("far", (-F.col("other")).alias("o"))).alias("w")
    return part.groupBy("medoid", "qid").agg(F.sum("total").alias("total"), F.count("*").alias("parts"), widest).select("medoid", "qid", "total", F.col("w.far").alias("far"), (-F.col("w.o")).alias("other"))


def medoid_update(points: DataFrame, assigned: DataFrame, kind: str = "numeric") -> DataFrame:
    """(medoid, new): within each cluster the entry with least summed distance. Quadratic in cluster size, as the method is.

    Sums in pieces leave a few entries that may be the least; these alone are summed once more, pair by pair.
    """
    assigned = materialise(assigned.select("qid", "medoid"), "of")
    sums = materialise(pair_statistics(points, assigned, kind), "sums")
    least = sums.groupBy("medoid").agg(F.min("total").alias("least"), F.count("*").alias("n"), F.max("far").alias("wide"))  # a row per cluster
    slack = F.lit(2e-6) + 2 * F.lit(BLOCK_LOSS) * F.col("n") * F.col("wide") + F.lit(1e-11) * F.col("least")
    open_ = sums.join(F.broadcast(least), "medoid").where(F.col("total") <= F.col("least") + slack).select(F.col("medoid").alias("of"), F.col("qid").alias("_q"))
    few = points.join(open_, F.col("qid") == F.col("_q")).drop("_q")
    other = points.join(assigned.select(F.col("qid").alias("_q"), "medoid"), F.col("qid") == F.col("_q")).select(F.col("medoid").alias("of"), *(F.col(c).alias(f"o_{c}") for c in ("qid", "num", "toks") if c in points.columns))
    pairs = few.join(other, "of")
    d = euclid(F.col("num"), F.col("o_num")) if kind == "numeric" else jaccard(F.col("toks"), F.col("o_toks")) if kind == "categorical" else mixed(F.col("num"), F.col("o_num"), F.col("toks"), F.col("o_toks"))
    exact = pairs.withColumn("d", d).groupBy("of", "qid").agg(F.round(F.sum("d"), 6).alias("sum"))
    return exact.groupBy("of").agg(F.min(F.struct("sum", "qid")).alias("b")).select(F.col("of").alias("medoid"), F.col("b.qid").alias("new"))


def farthest_first(points: DataFrame, k: int, kind: str = "numeric", chosen: list[int] | None = None) -> list[int]:
    """k ids: the smallest id, then repeatedly the entry farthest from all chosen so far; ``chosen`` are those found before.

    Each step is one pass with all chosen entries, a few rows, beside every entry.
    """
    chosen = list(chosen or [])
    if not chosen:
        points = materialise(points, "points")
        first = points.agg(F.min("qid")).head()[0]
        chosen = [first] if first is not None else []
    while chosen and len(chosen) < k:
        near = medoid_assign(points, points.where(F.col("qid").isin(chosen)), kind)
        top = near.where(~F.col("qid").isin(chosen)).orderBy(F.desc("dist"), "qid").select("qid").head()
        if top is None:
            break
        chosen.append(top["qid"])
    return chosen


def k_medoids(points: DataFrame, k: int, kind: str = "numeric", rounds: int = 10, init: str = "farthest", chosen: list[int] | None = None) -> tuple[list[int], float]:
    """(medoid ids, cost) by alternating assignment and medoid update until the medoids stay; ``chosen`` begin the farthest ones."""
    points = materialise(points, "points")
    medoids = farthest_first(points, k, kind, chosen) if init == "farthest" else [r["qid"] for r in random_sample(points, k).orderBy("pick_no").collect()]
    cost = float("inf")
    for _ in range(rounds):
        assigned = materialise(medoid_assign(points, points.where(F.col("qid").isin(medoids)), kind), "assigned")
        now = assigned.agg(F.sum("dist")).head()[0] or 0.0
        new = sorted(r["new"] for r in medoid_update(points, assigned, kind).collect())
        if now >= cost or new == sorted(medoids):
            return sorted(medoids), min(now, cost)
        cost, medoids = now, new
    return sorted(medoids), cost


def k_medoids_doubling(points: DataFrame, good_enough, start: int = 2, most: int = 1024, **options) -> list[int]:
    """Double the number of clusters until ``good_enough(medoids)``."""
    k, far = start, []
    points = materialise(points, "points")
    while True:
        if options.get("init", "farthest") == "farthest":  # the first k of 2k are the same
            far = farthest_first(points, k, options.get("kind", "numeric"), far)
        medoids, _ = k_medoids(points, k, chosen=far, **options)
        if good_enough(medoids) or k >= most:
            return medoids
        k *= 2


def distance_matrix(points: DataFrame, kind: str = "numeric", multiset: bool = False) -> tuple[list[int], np.ndarray]:
    """Ids and all distances of at most MAX_PAIRWISE entries."""
    rows = points.orderBy("qid").limit(MAX_PAIRWISE + 1).collect()
    if len(rows) > MAX_PAIRWISE:
        raise ValueError("too many entries for a distance matrix; sample first")
    num = np.array([r["num"] for r in rows]) if kind != "categorical" else None
    bags = [dict.fromkeys(r["toks"], 1) if not multiset else {t: r["toks"].count(t) for t in r["toks"]} for r in rows] if kind != "numeric" else None
    return [r["qid"] for r in rows], pairwise(num, bags, multiset)


def _medoids_of(ids: list[int], dist: np.ndarray, clusters: list[list[int]]) -> list[int]:
    return sorted(ids[min(c, key=lambda i: (round(float(dist[i, c].sum()), 9), ids[i]))] for c in clusters)


def hierarchical(points: DataFrame, k: int, linkage: str = "average", kind: str = "numeric") -> list[int]:
    """Medoids of k clusters: bottom-up with average linkage, or 'divisive' from the top."""
    if linkage != "divisive":
        from repsum.operators.linkage import agglomerative

        return agglomerative(points, k, kind)
    points = materialise(points, "points")
    if points.count() > MAX_PAIRWISE:
        return divisive(points, k, kind)
    ids, dist = distance_matrix(points, kind)
    n = len(ids)
    if n <= k:
        return ids
    clusters = [list(range(n))]
    while len(clusters) < k:
        wide = max(clusters, key=lambda c: (float(dist[np.ix_(c, c)].max()), -c[0]))
        inner = dist[np.ix_(wide, wide)]
        a, b = np.unravel_index(int(inner.argmax()), inner.shape)
        if inner[a, b] == 0:
            break
        near = inner[:, a] <= inner[:, b]
        clusters.remove(wide)
        clusters += [[wide[i] for i in np.flatnonzero(near)], [wide[i] for i in np.flatnonzero(~near)]]
    return _medoids_of(ids, dist, clusters)


def divisive(points: DataFrame, k: int, kind: str = "numeric") -> list[int]:
    """The divisive method without a matrix: the widest cluster is split between its two farthest entries.

    Only clusters that a split has made are compared anew, in pieces; clusters are a column of a table.
    """
    of = materialise(points.select("qid", F.lit(0).cast("long").alias("medoid")), "of")
    wide: dict[int, tuple] = {}
    fresh, made = [0], 1
    while True:
        found = pair_statistics(points, of.where(F.col("medoid").isin(fresh)), kind)
        for r in found.groupBy("medoid").agg(F.min("qid").alias("first"), F.max(F.struct("far", (-F.col("qid")).alias("q"), (-F.col("other")).alias("o"))).alias("w")).collect():  # a row per cluster
            wide[r["medoid"]] = (r["w"]["far"], -r["first"], -r["w"]["q"], -r["w"]["o"])
        if made >= k:
            break
        at = max(wide, key=lambda c: wide[c][:2])
        far, _, a, b = wide.pop(at)
        if far == 0:
            break
        own = points.join(of.where(F.col("medoid") == at).select(F.col("qid").alias("_q")), F.col("qid") == F.col("_q")).drop("_q")
        near = distances_to(own, points.where(F.col("qid").isin([a, b])), kind).groupBy("qid").agg(F.max(F.when(F.col("other") == a, F.col("dist"))).alias("da"), F.max(F.when(F.col("other") == b, F.col("dist"))).alias("db"))
        split = near.select("qid", F.when(F.col("da") <= F.col("db"), made * 2).otherwise(made * 2 + 1).cast("long").alias("medoid"))
        of = materialise(of.where(F.col("medoid") != at).unionByName(split), "of")
        fresh, made = [made * 2, made * 2 + 1], made + 1
    return sorted(r["new"] for r in medoid_update(points, of, kind).collect())


def dense_points(entries: DataFrame, numeric: list[str], toks: DataFrame) -> DataFrame:
    """(qid, num, toks): scaled numbers and (feature, token) names of each entry."""
    from repsum.functions.numeric import bounds

    edge = F.broadcast(bounds(entries, numeric))
    scaled = F.array(*(F.when(F.col(f"hi_{f}") > F.col(f"lo_{f}"), (F.col(f) - F.col(f"lo_{f}")) / (F.col(f"hi_{f}") - F.col(f"lo_{f}"))).otherwise(0.0) for f in numeric))
    num = entries.crossJoin(edge).select("qid", scaled.alias("num"))
    names = toks.groupBy("qid").agg(F.array_sort(F.collect_set(F.concat_ws("=", "feature", "token"))).alias("toks"))
    return num.join(names, "qid", "left").select("qid", "num", F.coalesce("toks", F.array().cast("array<string>")).alias("toks"))
