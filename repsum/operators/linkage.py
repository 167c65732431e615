"""Agglomerative clustering with average linkage whose pairs are never held: rows of distances are computed where they are needed."""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

#: Clusters whose mutual distances are held at once, as a matrix on the driver.
MATRIX = 1024
#: Entries of a tile of distances: rows, columns; tokens compared at once; sums of a batch of clusters.
ROWS, COLUMNS, TOKENS, SUMS = 128, 2048, 2048, 1 << 22
#: Pairs below which a step is computed on the driver: a job of Spark's takes longer.
LOCAL_PAIRS = 20_000_000
#: Digits, as a share of the widest distance, in which equal distances of different sums agree.
DIGITS = 12


@dataclass
class Points:
    """Different entries as arrays: numbers, the number of each one's set, tokens of set s at ``start[s]`` to ``start[s + 1]``, copies.

    Numbers come divided by the root of their count and, as the gaps of sets, by two where both count, so that distances are plain sums.
    """

    num: np.ndarray | None
    kind: np.ndarray | None
    start: np.ndarray
    token: np.ndarray
    weight: np.ndarray

    def sets(self, kinds: np.ndarray, names: np.ndarray) -> np.ndarray:
        """Which of the sorted ``names`` each set holds."""
        length = self.start[kinds + 1] - self.start[kinds]
        row = np.repeat(np.arange(len(kinds)), length)
        own = self.token[np.arange(len(row)) - np.repeat(np.cumsum(length) - length, length) + np.repeat(self.start[kinds], length)]
        at = np.minimum(np.searchsorted(names, own), len(names) - 1)
        held = np.zeros((len(kinds), len(names)), np.float32)
        hit = names[at] == own
        held[row[hit], at[hit]] = 1
        return held

    def jaccard(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        both = np.zeros((len(a), len(b)))
        names = np.unique(np.concatenate([self.token[self.start[k] : self.start[k + 1]] for k in a]))
        for begin in range(0, len(names), TOKENS):
            some = names[begin : begin + TOKENS]
            both += self.sets(a, some) @ self.sets(b, some).T
        size = (self.start[1:] - self.start[:-1]).astype(float)
        either = size[a][:, None] + size[b][None, :] - both
        return np.where(either > 0, 1 - both / np.where(either > 0, either, 1), 0.0)

    def distances(self, rows: np.ndarray, columns: np.ndarray) -> np.ndarray:
        out = np.zeros((len(rows), len(columns)))
        gap = np.empty_like(out)
        if self.num is not None:
            for f in range(self.num.shape[1]):
                np.subtract.outer(self.num[rows, f], self.num[columns, f], out=gap)
                out += np.multiply(gap, gap, out=gap)
            np.sqrt(out, out=out)
        if self.kind is not None:
            (a, at_a), (b, at_b) = (np.unique(self.kind[x], return_inverse=True) for x in (rows, columns))
            sets = self.jaccard(a, b) * (1.0 if self.num is None else 0.5)
            out += np.take(sets[:, at_b], at_a, axis=0, out=gap, mode="clip")
        return out


@dataclass
class Clusters:
    """Entries in the order of their clusters; cluster c has those at ``start[c]`` to ``start[c + 1]`` and ``size[c]`` with copies."""

    order: np.ndarray
    start: np.ndarray
    size: np.ndarray

    @staticmethod
    def of(label: np.ndarray, weight: np.ndarray) -> Clusters:
        n = int(label.max()) + 1
        return Clusters(np.argsort(label, kind="stable"), np.concatenate([[0], np.cumsum(np.bincount(label, minlength=n))]), np.bincount(label, weight, n))


def _sums(p: Points, c: Clusters, which: np.ndarray) -> np.ndarray:
    """Summed distances of the pairs of entries of each cluster in ``which`` with every cluster."""
    out = np.zeros((len(which), len(c.size)))
    rows = np.concatenate([c.order[c.start[x] : c.start[x + 1]] for x in which])
    own = np.repeat(np.arange(len(which)), c.start[which + 1] - c.start[which])
    single, copies = len(c.size) == len(c.order), bool((p.weight > 1).any())
    for begin in range(0, len(c.order), COLUMNS):
        columns = c.order[begin : begin + COLUMNS]
        first = int(np.searchsorted(c.start, begin, "right")) - 1
        last = int(np.searchsorted(c.start, begin + len(columns), "left"))
        cut = np.maximum(c.start[first:last] - begin, 0)
        for r in range(0, len(rows), ROWS):
            d = p.distances(rows[r : r + ROWS], columns)
            if copies:
                d *= p.weight[columns]
            d = d if single else np.add.reduceat(d, cut, axis=1)
            if copies:
                d *= p.weight[rows[r : r + ROWS]][:, None]
            o = own[r : r + ROWS]
            turn = np.flatnonzero(np.r_[True, o[1:] != o[:-1]])
            out[o[turn], first:last] += d if len(turn) == len(o) else np.add.reduceat(d, turn, axis=0)
    return out


def _nearest(p: Points, c: Clusters, which: np.ndarray, unit: float) -> tuple[np.ndarray, np.ndarray]:
    """Of each cluster the nearest other one by average distance, ties to the smaller, and how far it is."""
    d = _averages(_sums(p, c, which), c.size[which], c.size, unit)
    d[np.arange(len(which)), which] = np.inf
    near = d.argmin(axis=1)
    return near, d[np.arange(len(which)), near]


def _averages(sums: np.ndarray, a: np.ndarray, b: np.ndarray, unit: float) -> np.ndarray:
    """Average distances in units of the last digit that counts; the sums are overwritten."""
    sums *= (10.0**DIGITS / unit / a)[:, None]
    sums *= 1 / b
    return np.rint(sums, out=sums)


def _totals(p: Points, c: Clusters, rows: np.ndarray) -> np.ndarray:
    """Of each place in the order, the summed distance of its entry to its own cluster."""
    out = np.zeros(len(rows))
    own = np.searchsorted(c.start, rows, "right") - 1
    for x in np.unique(own):
        mine, members = np.flatnonzero(own == x), c.order[c.start[x] : c.start[x + 1]]
        for r in range(0, len(mine), ROWS):
            at = mine[r : r + ROWS]
            for begin in range(0, len(members), COLUMNS):
                columns = members[begin : begin + COLUMNS]
                out[at] += p.distances(c.order[rows[at]], columns) @ p.weight[columns]
    return out


class Steps:
    """Computes for numbered items, in batches of about the same work, on the driver or by Spark's tasks."""

    def __init__(self, spark, points: Points):
        self.spark, self.points, self.sent = spark, points, None

    def run(self, c: Clusters, items: np.ndarray, work: np.ndarray, most: int, f) -> list[tuple[np.ndarray, ...]]:
        """f(points, clusters, items) of every batch of at most ``most`` items, in order; f returns arrays."""
        if not len(items):
            return []
        begin, pairs = [0], 0
        for i, w in enumerate(work.tolist()):
            if pairs and (i - begin[-1] >= most or pairs + w > 16 * ROWS):
                begin.append(i)
                pairs = 0
            pairs += w
        batches = [items[a:b] for a, b in zip(begin, [*begin[1:], len(items)])]
        if int(work.sum()) * len(c.order) <= LOCAL_PAIRS:
            return [f(self.points, c, b) for b in batches]
        sc = self.spark.sparkContext
        self.sent = self.sent or sc.broadcast(self.points)
        points, state = self.sent, sc.broadcast((c, batches))

        def tasks(tables):
            for t in tables:
                for n in t.column("id").to_pylist():
                    own, of = state.value
                    got = f(points.value, own, of[n])
                    yield pa.RecordBatch.from_pydict({"n": pa.array([n], pa.int64()), "got": pa.array([[np.ascontiguousarray(x).tobytes() for x in got]], pa.list_(pa.binary())), "kinds": pa.array([[x.dtype.str for x in got]], pa.list_(pa.string()))})

        parts = min(len(batches), 4 * sc.defaultParallelism)
        got = self.spark.range(0, len(batches), 1, parts).mapInArrow(tasks, "n long, got array<binary>, kinds array<string>").toArrow().sort_by("n")
        state.unpersist()
        return [tuple(np.frombuffer(x, k) for x, k in zip(r["got"], r["kinds"])) for r in got.to_pylist()]

    def close(self) -> None:
        if self.sent:
            self.sent.unpersist()


def _joined(steps: Steps, unit: float) -> list[tuple[float, int, int]]:
    """(distance, a, b): all merges of the entries, clusters named by their first entry.

    Two clusters that are each other's nearest are merged whatever happens elsewhere: an average is
    no less than the lesser of what it is of. So a round merges all such pairs, and looks anew only for the
    nearest of clusters that were merged or whose nearest one was. The last MATRIX clusters are merged one by one.
    """
    p = steps.points
    n = len(p.weight)
    label, name = np.arange(n), np.arange(n)
    c, near, far, fresh, merges = Clusters.of(label, p.weight), np.zeros(n, int), np.zeros(n), np.arange(n), []
    while len(name) > MATRIX:
        work = c.start[fresh + 1] - c.start[fresh]
        got = steps.run(c, fresh, work, max(1, min(ROWS, SUMS // len(name))), lambda p, c, x: _nearest(p, c, x, unit))
        if got:
            near[fresh], far[fresh] = (np.concatenate(x) for x in zip(*got))
        all_ = np.arange(len(name))
        a = np.flatnonzero((near[near] == all_) & (all_ < near))
        if not len(a):  # equal but for rounding: the least pair
            a = np.lexsort((np.maximum(all_, near), np.minimum(all_, near), far))[:1]
        b = near[a]
        a, b = np.minimum(a, b), np.maximum(a, b)
        merges += zip(far[a].tolist(), name[a].tolist(), name[b].tolist())
        into, left = all_.copy(), np.ones(len(name), bool)
        into[b], left[b] = a, False
        touched = np.zeros(len(name), bool)
        touched[a] = touched[b] = True
        again = touched | touched[near]
        now = (np.cumsum(left) - 1)[into]
        label, near, far, fresh = now[label], now[near][left], far[left], np.flatnonzero(again[left])
        name = name[left]
        c = Clusters.of(label, p.weight)
    m = len(name)
    work = c.start[1:] - c.start[:-1]
    sums = np.concatenate([x.reshape(-1, m) for x, in steps.run(c, np.arange(m), work, max(1, min(ROWS, SUMS // m)), lambda p, c, x: (_sums(p, c, x),))])
    sums, size = (sums + sums.T) / 2, c.size.copy()
    d = _averages(sums.copy(), size, size, unit)
    np.fill_diagonal(d, np.inf)
    for _ in range(m - 1):
        a, b = sorted(int(x) for x in np.unravel_index(int(d.argmin()), d.shape))
        merges.append((float(d[a, b]), int(name[a]), int(name[b])))
        gone = np.isinf(d[a])
        sums[a] += sums[b]
        sums[:, a] = sums[a]
        size[a] += size[b]
        d[a] = _averages(sums[a : a + 1].copy(), size[a : a + 1], size, unit)[0]
        d[a, gone] = d[a, b] = np.inf
        d[:, a], d[b], d[:, b] = d[a], np.inf, np.inf
    return merges


def _first(merges: list[tuple[float, int, int]], n: int, most: int) -> np.ndarray:
    """Cluster of each of n entries after the ``most`` merges that come first by distance, ties to the smaller entries; a merge follows those of its parts."""
    last: dict[int, int] = {}
    waits, then = [0] * len(merges), [-1] * len(merges)
    for i, (_, a, b) in enumerate(merges):
        for x in (a, b):
            if x in last:
                then[last[x]] = i
                waits[i] += 1
        last[a] = i
    heap = [(*merges[i], i) for i in range(len(merges)) if not waits[i]]
    heapq.heapify(heap)
    root = list(range(n))
    for _ in range(most):
        _, a, b, i = heapq.heappop(heap)
        root[b] = a
        if then[i] >= 0:
            waits[then[i]] -= 1
            if not waits[then[i]]:
                heapq.heappush(heap, (*merges[then[i]], then[i]))
    for x in range(n):  # a cluster's name is its first entry, so the root of a smaller entry is final
        root[x] = root[root[x]]
    return np.unique(root, return_inverse=True)[1]


def _load(points: DataFrame, kind: str) -> tuple[np.ndarray, np.ndarray, Points]:
    """Ids in order, the different entry of each, and these. A missing number counts as 0, a missing set as empty."""
    columns = [c for c in ("num", "toks") if c != {"numeric": "toks", "categorical": "num"}.get(kind)]
    few = points.where("qid is not null").select("qid", *columns)
    if "toks" in columns:
        few = few.withColumn("toks", F.array_sort(F.array_distinct(F.coalesce("toks", F.array().cast("array<string>")))))
    table = few.toArrow().sort_by("qid")
    ids, num, kinds, start, token = table.column("qid").to_numpy(), None, None, np.zeros(1, int), np.zeros(0, int)
    keys: list[np.ndarray] = []
    if "num" in columns:
        lists = table.column("num").combine_chunks()
        num = np.nan_to_num(lists.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1)) + 0.0 if len(ids) else np.zeros((0, 0))
        keys += list(num.T)
    if "toks" in columns:
        lists = table.column("toks").combine_chunks()
        names = lists.flatten().dictionary_encode().indices.fill_null(-1).to_numpy(zero_copy_only=False)
        ends = lists.offsets.to_numpy() - (lists.offsets[0].as_py() if len(lists.offsets) else 0)
        known: dict[bytes, int] = {}
        kinds = np.zeros(len(ids), int)
        held = []
        for i in range(len(ids)):
            own = np.sort(names[ends[i] : ends[i + 1]])
            kinds[i] = known.setdefault(own.tobytes(), len(known))
            if kinds[i] == len(held):
                held.append(own)
        start = np.concatenate([[0], np.cumsum([len(x) for x in held])]).astype(int)
        token = np.concatenate(held) if held else token
        keys.append(kinds)
    if not len(ids):
        return ids, np.zeros(0, int), Points(num, kinds, start, token, np.zeros(0))
    if num is not None:
        num *= (1.0 if kinds is None else 0.5) / np.sqrt(max(1, num.shape[1]))
    order = np.lexsort((np.arange(len(ids)), *keys))
    new = np.r_[True, np.any([k[order][1:] != k[order][:-1] for k in keys], axis=0)] if keys else np.r_[True, np.zeros(len(ids) - 1, bool)]
    head = order[new]  # the first entry of each group of equal ones
    group = np.empty(len(ids), int)
    group[order] = np.argsort(np.argsort(head))[np.cumsum(new) - 1]
    head = np.sort(head)
    return ids, group, Points(num[head] if num is not None else None, kinds[head] if kinds is not None else None, start, token, np.bincount(group).astype(float))


def agglomerative(points: DataFrame, k: int, kind: str = "numeric") -> list[int]:
    """Medoids of k clusters, merged bottom-up by least average distance, ties to the smaller ids.

    Time is quadratic at least, as the method is; memory is not. The driver and every task hold the entries
    as arrays, a few numbers each, and tiles of distances. Equal entries are merged before all others and
    then counted, not compared.
    """
    ids, group, p = _load(points, kind)
    if len(ids) <= k:
        return ids.tolist()
    n = len(p.weight)
    first = np.zeros(n, int)
    first[group[::-1]] = np.arange(len(ids))[::-1]
    if n <= k:  # only equal entries are merged, those with the smallest ids first
        rest = np.setdiff1d(np.argsort(group, kind="stable"), first)
        alone = rest[np.lexsort((rest, group[rest]))][len(ids) - k :]
        return np.sort(ids[np.concatenate([first, alone])]).tolist()
    wide = 0.0 if p.kind is None else 1.0
    if p.num is not None:
        wide += float(np.linalg.norm(p.num.max(axis=0) - p.num.min(axis=0)))
    steps = Steps(points.sparkSession, p)
    label = _first(_joined(steps, wide), n, n - k)
    c = Clusters.of(label, p.weight)
    totals = np.concatenate([x for x, in steps.run(c, np.arange(n), np.ones(n, int), 4 * ROWS, lambda p, c, x: (_totals(p, c, x),))])
    steps.close()
    best = np.lexsort((c.order, np.round(totals, 9), label[c.order]))
    heads = best[np.r_[True, np.diff(label[c.order][best]) != 0]]
    return np.sort(ids[first[c.order[heads]]]).tolist()
