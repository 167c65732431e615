"""The submodular compressor: greedy choice of entries by smoothed log coverage per cost.

``vectors`` hold one row per entry: (qid, cost, tids, mults). The state is two arrays over the
domain: the target d and the multiplicities m of what has been picked. An entry's gain is
sum of d * (ln(m + c + gamma) - ln(m + gamma)) over its tokens; gains are rounded to 1e-9 and
ties go to the smallest id, so every strategy picks the same entries:

eager   scores every entry in every round, one distributed pass per pick.
fenced  gains only shrink as the summary grows, so stale gains bound the present ones. A pass
        scores everything once and brings the best ``pool`` entries to the driver, where the
        best is picked as long as it beats the *fence*, the best bound left outside. Only
        when the fence is reached is another pass due.
lazy    the same over all entries of a log of at most ``MAX_POOL``, without a fence.

gamma 'limit' is the order that gains have as gamma goes to 0; gamma 'cover' counts target mass
newly covered and nothing else.

The best single entry that fits is kept as a safeguard for budgets over unequal costs.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  (makes pa.compute available)
from pyspark.sql import DataFrame, SparkSession, functions as F

from repsum.operators.blocks import BLOCK, Blocks, Entries, of_batch
from repsum.operators.features import with_domain
from repsum.plans.scratch import materialise

GAMMA = 1e-25
DIGITS = 9
POOL = 4096
#: Rows that a task hands over at least.
LEAST_OF_TASK = 8
#: Entries that the lazy strategy takes at most.
MAX_POOL = 1 << 18
#: Entries that a pass brings to the driver at most; more passes do the rest. Wider pools hardly serve more picks, but cost time and memory.
PASS_POOL = 1 << 16
#: Tokens of all those entries together; pools of long entries hold fewer of them.
POOL_TOKENS = 1 << 23


@dataclass
class Pick:
    qid: int
    gain: float
    cost: float
    tids: np.ndarray
    mults: np.ndarray


@dataclass
class Result:
    picks: list[Pick] = field(default_factory=list)
    passes: int = 0
    evaluations: int = 0
    winner: str = "greedy"

    def ids(self) -> list[int]:
        return [p.qid for p in self.picks]


def _parts(weight: np.ndarray, have: np.ndarray, c: np.ndarray, gamma: float | str, most: bool) -> list[np.ndarray]:
    """What tokens of target ``weight`` that a summary has ``have`` times add to an entry's gain when they come ``c`` times more."""
    if gamma == "cover":
        return [np.where(have == 0, weight, 0.0)]
    if gamma == "limit":
        kept = np.where(have == 0, 1, have)
        grown = np.log(kept + c) - np.log(kept)
        return [np.where(have == 0, weight, 0.0), weight * np.where(have == 0, np.log(c), grown), *([weight * grown] if most else [])]
    return [weight * (np.log(have + c + gamma) - np.log(have + gamma))]


def gain_of(d: np.ndarray, m: np.ndarray, tids: np.ndarray, mults: np.ndarray, starts: np.ndarray, gamma: float | str, most: bool = False) -> np.ndarray:
    """Gains of entries that lie end to end in ``tids``; ``starts`` are their first positions.

    For gamma 'limit' the result has two columns: target mass newly covered, then the growth of
    sum d * ln m. With ``most`` a third one has the most that this growth can be under any larger
    summary: a token grows by ln c when it is met first, by ln(1 + c) at most once it is covered, and
    by ever less after that.
    """
    parts = _parts(d[tids], m[tids], mults.astype(np.float64), gamma, most)
    if not len(starts):
        return np.stack(parts, axis=1)[:0] if gamma == "limit" else parts[0][:0]
    got = [np.add.reduceat(p, starts) for p in parts]
    return np.stack(got, axis=1) if gamma == "limit" else got[0]


def keys_of(gain: np.ndarray, cost: np.ndarray) -> np.ndarray:
    """Comparable values of gains per cost, a row each and larger first; free entries with a gain come before all."""
    free = cost <= 0
    per = np.where(free, 1.0, cost)
    rounded = np.round(gain, DIGITS)
    if gain.ndim == 2:
        first, second = rounded[:, 0], rounded[:, 1]
        some, own = (first > 0) | (second > 0), np.stack([first / per, second / per], axis=1)
    else:
        first, some = rounded, rounded > 0
        own = np.stack([np.round(rounded / per, DIGITS), np.zeros(len(gain))], axis=1)
    return np.where(free[:, None], np.stack([np.where(some, np.inf, 0.0), np.where(some, first, 0.0)], axis=1), own)


#: Entries of a front at least; fronts are widened where all entries are scored more often than it pays.
CHUNK = 256


def bounds_of(gain: np.ndarray, cost: np.ndarray) -> np.ndarray:
    """What keys_of() gives at most under any larger summary: for 'limit' its second part may still grow, other keys only fall."""
    return keys_of(gain[:, [0, 2]] if gain.ndim == 2 else gain, cost)


#: Results of gains that are kept in a table over (token, multiplicity) at most, and multiplicities that a pass has in it.
TABLE, WIDE = 1 << 22, 8


class Gains:
    """Gains under a summary ``m``, which it adds picks to. What a pair of token and multiplicity adds is in a table where that is small."""

    def __init__(self, d: np.ndarray, m: np.ndarray, gamma, wide: int) -> None:
        self.d, self.m, self.gamma = d, m, gamma
        self.wide = wide if len(d) * wide <= TABLE else 0
        if self.wide:
            self.parts = self._rows(np.arange(len(d)))

    def _rows(self, tids: np.ndarray) -> list[np.ndarray]:
        c = np.tile(np.arange(self.wide, dtype=np.float64), len(tids))
        with np.errstate(divide="ignore", invalid="ignore"):  # no entry has a token zero times
            return _parts(np.repeat(self.d[tids], self.wide), np.repeat(self.m[tids], self.wide), c, self.gamma, True)

    def codes(self, entries: Entries) -> np.ndarray | None:
        """Places in the table, or none if it does not have them all."""
        if not self.wide or len(entries.mults) and int(entries.mults.max()) >= self.wide:
            return None
        return entries.tids.astype(np.int64) * self.wide + entries.mults

    def add(self, p: Pick) -> None:
        self.m[p.tids] += p.mults
        if self.wide:
            at = (p.tids[:, None] * self.wide + np.arange(self.wide)).ravel()
            for part, row in zip(self.parts, self._rows(p.tids)):
                part[at] = row

    def of(self, entries: Entries, codes: np.ndarray | None, starts: np.ndarray, full: np.ndarray | None) -> np.ndarray:
        """A gain an entry, three for 'limit' as gain_of() has them; ``full`` are those with tokens if some have none."""
        n = len(entries)
        gain = np.zeros((n, 3) if self.gamma == "limit" else n)
        if codes is None:
            some = np.arange(n) if full is None else full
            gain[some] = gain_of(self.d, self.m, entries.tids, entries.mults, starts[some], self.gamma, most=True)
        elif len(codes):
            for i, part in enumerate(self.parts):
                own = np.add.reduceat(part[codes], starts if full is None else starts[full])
                to = gain if gain.ndim == 1 else gain[:, i]
                if full is None:
                    to[:] = own
                else:
                    to[full] = own
        return gain


class Scored:
    """Entries in memory, laid out for being scored again and again."""

    def __init__(self, entries: Entries, gains: Gains) -> None:
        self.entries, self.gains, self.codes, self.starts = entries, gains, gains.codes(entries), entries.starts()
        self.full = np.flatnonzero(entries.size) if len(entries) and not entries.size.min() else None

    def __len__(self) -> int:
        return len(self.entries)

    def now(self) -> np.ndarray:
        return self.gains.of(self.entries, self.codes, self.starts, self.full)


def _first(a: np.ndarray, qid: np.ndarray, some: np.ndarray) -> int:
    """Of ``some``, the row of ``a`` that comes first: larger ones do, ties go to the smallest id."""
    for part in (0, 1):
        own = a[some, part]
        some = some[own == own.max()]
    return int(some[np.argmin(qid[some])])


def _largest(a: np.ndarray, n: int) -> np.ndarray:
    """Which ``n`` rows of ``a`` are largest, as a mask; ties in both columns are settled anyhow."""
    out = np.zeros(len(a), bool)
    edge = np.partition(a[:, 0], len(a) - n)[len(a) - n]
    out[a[:, 0] > edge] = True
    tied = np.flatnonzero(a[:, 0] == edge)
    out[tied[np.argpartition(-a[tied, 1], min(n - int(out.sum()), len(tied)) - 1)[: n - int(out.sum())]]] = True
    return out


def pick_of(entries: Entries, at: int, gain: float, start: int) -> Pick:
    tids, mults = (x[start : start + int(entries.size[at])].astype(np.int64) for x in (entries.tids, entries.mults))
    return Pick(int(entries.qid[at]), gain, float(entries.cost[at]), tids, mults)


def lazy(entries: list[Pick] | Entries, d: np.ndarray, m: np.ndarray, left: float, count: int | None, gamma, fence: tuple | None, result: Result, keys: tuple[np.ndarray, np.ndarray] | None = None) -> float:
    """Pick from ``entries`` while the best of them beats ``fence``; updates ``m`` and returns the budget left.

    ``keys`` and their bounds are exact under the present summary (scored here if not given) and ``fence``
    is (bound, bound, qid) of the best entry outside. The entries of largest bounds are a front that is
    scored anew after each pick, and the best bound behind it is a fence of its own; when that is reached all
    entries are scored, those behind ``fence`` dropped, and the next front is taken.
    """
    entries = Entries.of(entries) if isinstance(entries, list) else entries
    gains = Gains(d, m, gamma, int(entries.mults.max(initial=0)) + 1)
    pool, size, start = Scored(entries, gains), CHUNK, len(result.picks)
    while count is None or len(result.picks) < count:
        if keys is None:
            gain = pool.now()
            key, bound = keys_of(gain, pool.entries.cost), bounds_of(gain, pool.entries.cost)
            result.evaluations += len(pool)
        else:
            (key, bound), gain, keys = keys, pool.entries.gain, None
        live = pool.entries.cost <= left  # the budget only falls
        if fence is not None:  # what falls behind the fence cannot be picked here any more
            live &= bound[:, 0] >= fence[0]
        if not live.any():
            break
        if live.sum() < len(pool):
            pool, key, bound, gain = Scored(pool.entries.take(live), gains), key[live], bound[live], gain[live]
        own, n = pool.entries, len(pool)
        ahead, ends = (_largest(bound, size) if size < n else np.ones(n, bool)), [(-fence[0], -fence[1], fence[2])] if fence is not None else []
        if size < n:
            at = _first(bound, own.qid, np.flatnonzero(~ahead))
            ends.append((-bound[at, 0], -bound[at, 1], own.qid[at]))
        end, places = min(ends, default=None), np.flatnonzero(ahead)
        front, before = Scored(own.take(places), gains), len(result.picks)
        open_ = np.ones(len(front), bool)
        while count is None or len(result.picks) < count:
            found = front.now()
            result.evaluations += len(front)
            some = np.flatnonzero(open_ & (front.entries.cost <= left))
            if not len(some):
                break
            k = keys_of(found, front.entries.cost)
            lead = _first(k, front.entries.qid, some)
            if end is not None and (-k[lead, 0], -k[lead, 1], front.entries.qid[lead]) >= end:
                break
            p = pick_of(front.entries, lead, float(found[lead, 0] if found.ndim == 2 else found[lead]), int(front.starts[lead]))
            open_[lead] = False
            gains.add(p)
            left -= p.cost
            result.picks.append(p)
        made, gone = len(result.picks) - before, places[~open_]
        if not made:  # a bound behind the front beats every key in it: the next pick is made by keys
            lead = _first(key, own.qid, np.arange(n))
            if fence is not None and (-key[lead, 0], -key[lead, 1], own.qid[lead]) >= (-fence[0], -fence[1], fence[2]):
                break
            p = pick_of(own, lead, float(gain[lead, 0] if gain.ndim == 2 else gain[lead]), int(pool.starts[lead]))
            gains.add(p)
            left -= p.cost
            result.picks.append(p)
            gone = np.array([lead])
        size = max(CHUNK, size * 2 if made * size < n else size // 2 if made * size > 4 * n else size)
        rest = np.ones(n, bool)
        rest[gone] = False
        if not rest.any():
            break
        pool = Scored(own.take(rest), gains)
    return left


_PASS = "part int, k0 double, k1 double, u0 double, u1 double, qid long, outside boolean, cost double, gain double, tids binary, mults binary"


def _front(part: np.ndarray, by: np.ndarray, qid: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, place) of the first ``most`` entries of each part, by part and in it by falling ``by``, then id."""
    order = np.lexsort((qid, -by[:, 1], -by[:, 0], part))
    own = part[order]
    new = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]])) if len(own) else np.zeros(0, np.int64)
    place = np.arange(len(own)) - np.repeat(new, np.diff(np.append(new, len(own))))
    return order[place < most], place[place < most]


def score_pass(vectors: DataFrame | Blocks, d: np.ndarray, m: np.ndarray, left: float | np.ndarray, picked: list[int], gamma, want: int, exact: bool = False, parts: int = 1, alone: bool = False) -> DataFrame:
    """The ``want`` entries of largest bounds (keys, if ``exact``) of every task and part that still fit, and the next one without its tokens, marked ``outside``.

    With several ``parts``, which the entries' hashes decide on, ``d`` and ``m`` have a row and ``left`` a
    value for each; a part with nothing left, below zero, is passed over. ``alone`` scores every entry as if it cost 1.
    """
    table = vectors.table if isinstance(vectors, Blocks) else vectors.select("qid", "cost", "tids", "mults")
    shared = table.sparkSession.sparkContext.broadcast((d.ravel(), m.ravel(), np.broadcast_to(left, parts), np.sort(np.array(picked, np.int64))))
    width = len(d.ravel()) // parts

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d, m, left, gone = shared.value
        gains = Gains(d, m, gamma, WIDE)
        held: list[tuple] = []
        rows, floor = 0, (np.full(parts, -np.inf) if parts <= 1 << 16 else None)

        def cut(rows: list[tuple]) -> tuple:
            part, key, most, gain = (np.concatenate([r[i] for r in rows]) for i in range(4))
            entries = Entries.joined([r[4] for r in rows])
            some, place = _front(part, key if exact else most, entries.qid, want + 1)
            if floor is not None:  # the last of a full part: nothing below it is handed over
                last = some[place == want]
                floor[part[last]] = (key if exact else most)[last, 0]
            return part[some], key[some], most[some], gain[some], entries.take(some), place

        for batch in batches:
            for entries, hashes in of_batch(batch):
                part = np.zeros(len(entries), np.int64) if parts == 1 else hashes.astype(np.int64) % parts
                ok = np.flatnonzero(entries.cost <= left[part])
                if len(ok) < len(entries):
                    entries, part = entries.take(ok), part[ok]
                moved = entries if parts == 1 else Entries(entries.qid, entries.cost, entries.gain, entries.size, entries.tids + np.repeat(part * width, entries.size), entries.mults)
                gain = Scored(moved, gains).now()
                cost = np.ones(len(entries)) if alone else entries.cost
                key, most = keys_of(gain, cost), bounds_of(gain, cost)
                ok = np.arange(len(entries)) if floor is None else np.flatnonzero((key if exact else most)[:, 0] >= floor[part])
                if len(gone):
                    ok = ok[gone[np.minimum(np.searchsorted(gone, entries.qid[ok]), len(gone) - 1)] != entries.qid[ok]]
                if not len(ok):
                    continue
                held.append((part[ok], key[ok], most[ok], gain[ok, 0] if gamma == "limit" else gain[ok], entries.take(ok)))
                rows += len(ok)
                if rows > 2 * (want + 1) * parts + BLOCK:
                    held = [cut(held)[:5]]
                    rows = len(held[0][0])
        if held:
            part, key, most, gain, entries, place = cut(held)
            inside = place < want
            for a in range(0, len(part), BLOCK):
                at = np.arange(a, min(a + BLOCK, len(part)))
                some = entries.take(at)
                kept, size = np.repeat(inside[at], some.size), np.where(inside[at], some.size, 0)
                ends = pa.py_buffer((np.concatenate([[0], np.cumsum(size)]) * 4).astype(np.int32))
                cells = {name: pa.Array.from_buffers(pa.binary(), len(at), [None, ends, pa.py_buffer(x[kept].astype(np.int32))]) for name, x in (("tids", some.tids), ("mults", some.mults))}
                own = {"part": part[at].astype(np.int32), "k0": key[at, 0], "k1": key[at, 1], "u0": most[at, 0], "u1": most[at, 1], "qid": some.qid, "outside": ~inside[at], "cost": some.cost, "gain": gain[at]}
                yield pa.RecordBatch.from_pydict({k: pa.array(v) for k, v in own.items()} | cells)

    return table.mapInArrow(run, _PASS)


def _share(want: int, tasks: int) -> int:
    """Rows that a task hands over: its fair share four times over."""
    return min(want, max(LEAST_OF_TASK, -(-4 * want // max(1, tasks))))


def _inside(found: pa.Table, want: int, exact: bool) -> tuple[Entries, tuple[np.ndarray, np.ndarray], tuple | None]:
    key, most = (np.stack([found.column(a).to_numpy(), found.column(b).to_numpy()], axis=1) for a, b in (("k0", "k1"), ("u0", "u1")))
    cut = np.flatnonzero(found.column("outside").to_numpy())
    n = min([want, found.num_rows, *cut[:1].tolist()])
    out = key if exact else most
    fence = (float(out[n, 0]), float(out[n, 1]), found.column("qid")[n].as_py()) if n < found.num_rows else None
    return Entries.of_table(found.slice(0, n)), (key[:n].copy(), most[:n].copy()), fence


def _best(vectors: DataFrame | Blocks, d, m, left, picked, gamma, want: int, tasks: int = 1, exact: bool = False, alone: bool = False) -> tuple[Entries, tuple[np.ndarray, np.ndarray], tuple | None]:
    """(entries of the largest bounds, their keys and bounds, bound and id of the best one left out): at most ``want`` entries.

    Every task hands over its fair share four times over, not ``want`` rows, so what meets in one place
    does not grow with the tasks beyond a few rows of each; what a task leaves out bounds the fence.
    With ``exact`` keys take the place of bounds; the first entry is then the next pick.
    """
    by = ("k0", "k1") if exact else ("u0", "u1")
    found = score_pass(vectors, d, m, left, picked, gamma, _share(want, tasks), exact, alone=alone)
    return _inside(found.orderBy(*map(F.desc, by), F.asc("qid")).limit(want + 1).toArrow(), want, exact)


def _best_of_parts(blocks: Blocks, d, m, left: np.ndarray, picked, gamma, want: int, tasks: int, exact: bool) -> dict[int, tuple]:
    """_best() of each part, all in one pass; a few thousand rows a part reach the driver."""
    found = score_pass(blocks, d, m, left, picked, gamma, _share(want, tasks), exact, len(left)).toArrow()
    part = found.column("part").to_numpy()
    by = np.stack([found.column(x).to_numpy() for x in (("k0", "k1") if exact else ("u0", "u1"))], axis=1)
    order, _ = _front(part, by, found.column("qid").to_numpy(), want + 1)
    return {int(p): _inside(found.take(pa.array(order[part[order] == p])), want, exact) for p in np.unique(part)}


def _as_pick(r) -> Pick:
    return Pick(r["qid"], r["gain"], r["cost"], np.array(r["tids"], np.int64), np.array(r["mults"], np.int64))


def compress(vectors: DataFrame | Blocks, d: np.ndarray, budget: float, gamma: float | str = GAMMA, strategy: str = "fenced", pool: int = POOL, unit: bool = True, include: list[Pick] | None = None, exclude: list[int] | None = None, safeguard: bool = True, most: int | None = None) -> Result:
    """Pick entries within ``budget``; ``unit`` says that every cost is 1, so the budget is a count.

    ``include`` is picked before anything else and paid for, ``exclude`` never; ``most`` bounds the picks.
    """
    result, m, left = Result(), np.zeros(len(d)), float(budget)
    hidden = list(exclude or [])
    for p in include or []:
        m[p.tids] += p.mults
        left -= p.cost
        result.picks.append(p)
    count = min((c for c in (int(budget) if unit else None, most) if c is not None), default=None)
    want = 1 if strategy == "eager" else min(pool, PASS_POOL, MAX_POOL)
    if strategy == "lazy" and (vectors.rows() if isinstance(vectors, Blocks) else vectors).limit(MAX_POOL + 1).count() > MAX_POOL:
        raise ValueError(f"the lazy strategy holds all entries at once; more than {MAX_POOL} need the fenced one")
    single: Pick | None = None
    if not unit and safeguard and not result.picks:
        found, *_ = _best(vectors, d, m, left, hidden, gamma, 1, exact=True, alone=True)
        if len(found):
            single = pick_of(found, 0, float(found.gain[0]), 0)
    tasks, most_, alone = (vectors.table if isinstance(vectors, Blocks) else vectors).rdd.getNumPartitions(), MAX_POOL, strategy == "eager"
    while count is None or len(result.picks) < count:
        take = MAX_POOL if strategy == "lazy" else 1 if alone else min(want, most_)
        inside, keys, fence = _best(vectors, d, m, left, hidden + result.ids(), gamma, take, 1 if strategy == "lazy" else tasks, alone)
        result.passes += 1
        result.evaluations += len(inside) if strategy == "lazy" else 0
        if not len(inside):
            break
        before, most_ = len(result.picks), max(1, min(MAX_POOL, POOL_TOKENS // max(1, int(inside.size.mean()))))
        left = lazy(inside, d, m, left, before + 1 if alone else count, gamma, None if alone else fence, result, keys)
        if fence is None and strategy != "eager":
            break
        alone = strategy == "eager" or len(result.picks) == before  # a bound beats every key: the next pick is made by keys
        if strategy == "fenced" and len(result.picks) - before < max(64, before // 2):
            want = min(4 * want, PASS_POOL, MAX_POOL)  # gains have flattened: a wider pool saves passes
    if single is not None and value(d, [single], gamma) > value(d, result.picks, gamma):
        result.picks, result.winner = [single], "single"
    return result


def value(d: np.ndarray, picks: list[Pick], gamma) -> tuple | float:
    """G of a set of picks; for 'limit' the pair to compare in order."""
    m = np.zeros(len(d))
    for p in picks:
        m[p.tids] += p.mults
    hit = m > 0
    if gamma == "cover":
        return float(d[hit].sum())
    if gamma == "limit":
        return round(float(d[hit].sum()), 12), round(float((d[hit] * np.log(m[hit])).sum()), 12)
    return float((d[hit] * (np.log(m[hit] + gamma) - np.log(gamma))).sum())


def target_array(dom: DataFrame, target: DataFrame | None = None, weights: DataFrame | None = None) -> np.ndarray:
    """d by tid: shares of the log, or a given target, times feature weights (a weight of one over the number of features changes nothing)."""
    rows = dom
    if target is not None:
        rows = rows.join(target.select("feature", "token", "d"), ["feature", "token"], "left")
    if weights is not None:
        rows = rows.join(F.broadcast(weights.select("feature", "w")), "feature")
    share = F.coalesce("d", F.lit(0.0)) if target is not None else F.col("freq").cast("double")
    scale = F.col("w") if weights is not None else F.lit(1.0)
    got = rows.select("tid", share.alias("x"), scale.alias("w")).toPandas().sort_values("tid")  # numbers only, of a checked domain
    d = got["x"].to_numpy(float) if target is not None else got["x"].to_numpy(float) / got["x"].sum()
    if weights is not None:
        d = d * got["w"].to_numpy(float) * rows.select("feature").distinct().count()
    return d


def trace(result: Result, d: np.ndarray, feature: np.ndarray, gamma, beta: float = 0.5) -> list[dict]:
    """One row per pick: G, both coverages, both representativities and the blended score of the prefix."""
    kinds, own = np.unique(feature, return_inverse=True)
    size = np.bincount(own, minlength=len(kinds))
    m, hit, out = np.zeros(len(d)), np.zeros(len(kinds)), []
    g = 0.0
    for n, p in enumerate(result.picks, 1):
        new = p.tids[m[p.tids] == 0]
        if not isinstance(gamma, str):
            g += float((d[p.tids] * (np.log(m[p.tids] + p.mults + gamma) - np.log(m[p.tids] + gamma))).sum())
        m[p.tids] += p.mults
        hit += np.bincount(own[new], minlength=len(kinds))
        alpha = hit / size
        gap = np.abs(m / max(m.sum(), 1) - d)
        row = {"pick_no": n, "qid": p.qid, "gain": p.gain, "cost": p.cost, "g": g, "alpha_min": float(alpha.min()), "alpha_avg": float(alpha.mean()), "rho_l1": float(1 - gap.sum() / 2), "rho_linf": float(1 - gap.max())}
        row["score"] = beta * row["alpha_avg"] + (1 - beta) * row["rho_l1"]
        out.append(row)
    return out


def feature_scores(picks: list[Pick], d: np.ndarray, feature: np.ndarray, kinds: list[str]) -> list[tuple[str, float, float]]:
    """(feature, coverage, representativity) of a summary with shares within each feature."""
    m = np.zeros(len(d))
    for p in picks:
        m[p.tids] += p.mults
    size, hit = np.bincount(feature, minlength=len(kinds)), np.bincount(feature, weights=m > 0, minlength=len(kinds))
    have, want = np.bincount(feature, weights=m, minlength=len(kinds)), np.bincount(feature, weights=d, minlength=len(kinds))
    gap = np.abs(m / np.maximum(have, 1)[feature] - d / np.where(want > 0, want, 1)[feature])
    lost = np.bincount(feature, weights=gap, minlength=len(kinds))
    return [(k, float(hit[i] / size[i]), float(1 - lost[i] / 2) if have[i] else 0.0) for i, k in enumerate(kinds)]


def best_prefix(rows: list[dict]) -> int:
    """Length of the prefix with the best blended score; greedy prefixes nest, so one run serves every size."""
    return max(rows, key=lambda r: (r["score"], -r["pick_no"]))["pick_no"] if rows else 0


def size_for(rows: list[dict], score: float) -> int | None:
    """Smallest prefix that reaches a score."""
    return next((r["pick_no"] for r in rows if r["score"] >= score), None)


TRACE = "pick_no int, qid long, gain double, cost double, g double, alpha_min double, alpha_avg double, rho_l1 double, rho_linf double, score double"


def summary(spark: SparkSession, result: Result) -> DataFrame:
    """(pick_no, qid, gain, cost)."""
    rows = [(n, int(p.qid), float(p.gain), float(p.cost)) for n, p in enumerate(result.picks, 1)]
    return spark.createDataFrame(rows, "pick_no int, qid long, gain double, cost double")


def collapse(vectors: DataFrame, keep: int) -> DataFrame:
    """One row per distinct (cost, vector) and copy number below ``keep``: copies beyond the budget can never be picked.

    Equal entries tie, and ties go to the smallest id, so only each vector's ``keep`` smallest
    ids matter. Row numbers are pruned before the shuffle.
    """
    from pyspark.sql import Window

    by = Window.partitionBy("cost", "tids", "mults").orderBy("qid")
    return vectors.withColumn("_n", F.row_number().over(by)).where(F.col("_n") <= keep).drop("_n")


def gains_by_join(toks: DataFrame, target: DataFrame, state: DataFrame, gamma: float) -> DataFrame:
    """(qid, gain) with the state as a table (feature, token, m): the pass for domains beyond a broadcast."""
    have = target.join(state.select("feature", "token", "m"), ["feature", "token"], "left").select("feature", "token", "d", F.coalesce("m", F.lit(0)).alias("m"))
    one = F.col("d") * (F.log(F.col("m") + F.col("mult") + F.lit(gamma)) - F.log(F.col("m") + F.lit(gamma)))
    return with_domain(toks, have).groupBy("qid").agg(F.sum(one).alias("gain"))


def compress_by_join(toks: DataFrame, target: DataFrame, budget: int, gamma: float = GAMMA, pool: int = 256) -> DataFrame:
    """(pick_no, qid, gain): plain greedy over a domain of any size; nothing over the domain is shipped or collected.

    ``target`` is (feature, token, d). A pass joins tokens to target and counts, and keeps the best
    ``pool`` entries. Their tokens alone, a bounded table, are scored again after each pick; as gains
    only shrink, picks go on until the best gain left outside the pool might win, then the next pass is due.
    """
    spark, picked = toks.sparkSession, []
    state = target.select("feature", "token", F.lit(0).cast("long").alias("m")).where("false")
    while len(picked) < budget:
        gains = gains_by_join(toks.where(~F.col("qid").isin([q for q, _ in picked])) if picked else toks, target, state, gamma)
        top = gains.select("qid", F.round("gain", DIGITS).alias("gain")).orderBy(F.desc("gain"), "qid").limit(pool + 1).collect()
        if not top:
            break
        fence = (top[pool]["gain"], 0.0, top[pool]["qid"]) if len(top) > pool else None
        inside = [r["qid"] for r in top[:pool]]
        own = materialise(toks.where(F.col("qid").isin(inside)).join(target, ["feature", "token"]).join(state, ["feature", "token"], "left").select("qid", "feature", "token", "mult", "d", F.coalesce("m", F.lit(0)).alias("m")), "pool").toPandas()
        names = own["feature"] + "\0" + own["token"]
        tid = names.factorize()[0]
        m, d = np.zeros(tid.max(initial=-1) + 1), np.zeros(tid.max(initial=-1) + 1)
        m[tid], d[tid] = own["m"].to_numpy(float), own["d"].to_numpy(float)
        at = own.groupby("qid").indices
        picks = [Pick(r["qid"], r["gain"], 1.0, tid[at[r["qid"]]].astype(np.int64), own["mult"].to_numpy(np.int64)[at[r["qid"]]]) for r in top[:pool]]
        keys = np.array([(p.gain, 0.0) for p in picks])
        got = Result()
        lazy(picks, d, m, float(budget), budget - len(picked), gamma, fence, got, (keys, keys.copy()))
        picked += [(p.qid, p.gain) for p in got.picks]
        chosen = toks.where(F.col("qid").isin([p.qid for p in got.picks])).select("feature", "token", F.col("mult").alias("m"))
        state = materialise(state.unionByName(chosen).groupBy("feature", "token").agg(F.sum("m").alias("m")), "state")  # tokens of the summary only
    return spark.createDataFrame([(n, q, g) for n, (q, g) in enumerate(picked, 1)], "pick_no int, qid long, gain double")
