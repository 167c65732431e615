"""From the rows that a log's entries are made of to its domain and packed vectors, each row shuffled once.

``Rows`` says what the columns are. Rows of an entry meet in one task, which writes blocks with token
numbers of their own; the domain is summed from the blocks' few words, and a map over the blocks gives the
tokens their ids. The result is that of domain() and pack() over tokens() of the same log.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from repsum.operators.blocks import BLOCK, SCHEMA, Blocks, Entries, batch_of, rows_of, written

#: Numeric values of entries: name to (entry of each value, values).
Numbers = dict[str, tuple[np.ndarray, np.ndarray]]


@dataclass
class Rows:
    """``table`` has qid and other columns, a row or more for each entry.

    Values of ``counted`` columns are counted per entry, each value of ``single`` ones stands for itself; nulls
    yield nothing. ``numbers`` gets the rows of whole entries, sorted by qid, with the entry of each row and where entries start.
    """

    table: DataFrame
    counted: list[str]
    single: list[str]
    numbers: Callable[[pa.Table, np.ndarray, np.ndarray], Numbers]


_CODED = "qid binary, cost binary, size binary, codes binary, mults binary, features array<string>, words array<string>, counts array<long>, numbers array<string>, at array<binary>, values array<binary>, lows array<long>, highs array<long>"


def coded(rows: Rows, cost: str | None = None) -> DataFrame:
    """Blocks of entries with numbered words, and the numeric values beside them; ``cost`` names a numeric feature that is an entry's cost, else it is 1."""

    counted, single, numbers_of = rows.counted, rows.single, rows.numbers

    def block(table: pa.Table, start: np.ndarray, entry: np.ndarray, qid: np.ndarray) -> dict:
        n, features, words, who, code = len(start), [], [], [], []
        times = []
        for name in [*counted, *single]:
            column = table.column(name).combine_chunks()
            column = column if pa.types.is_string(column.type) else column.cast(pa.string())
            coded_ = column.dictionary_encode()
            at = np.flatnonzero(coded_.is_valid().to_numpy(zero_copy_only=False))
            own = coded_.indices.take(pa.array(at)).to_numpy() + len(words)
            new = coded_.dictionary.to_pylist()
            e, t = entry[at], np.ones(len(at), np.int64)
            if name in counted and len(at):
                top = len(words) + len(new)
                both, t = np.unique(e * top + own, return_counts=True)
                e, own = both // top, both % top
            features += [name] * len(new)
            words += new
            who.append(e)
            code.append(own)
            times.append(t)
        who, code, times = np.concatenate(who), np.concatenate(code), np.concatenate(times)
        order = np.argsort(who, kind="stable")
        numbers = numbers_of(table, entry, start)
        price = np.ones(n)
        if cost is not None:
            price = np.full(n, np.nan)
            price[numbers[cost][0]] = numbers[cost][1]
        return {
            "qid": qid[start].tobytes(), "cost": price.tobytes(), "size": np.bincount(who, minlength=n).astype(np.int32).tobytes(), "codes": code[order].astype(np.int32).tobytes(), "mults": times[order].astype(np.int32).tobytes(),
            "features": features, "words": words, "counts": np.bincount(code, weights=times, minlength=len(words)).astype(np.int64).tolist(),
            "numbers": list(numbers), "at": [a.astype(np.int32).tobytes() for a, _ in numbers.values()], "values": [v.astype(np.int64).tobytes() for _, v in numbers.values()],
            "lows": [int(v.min()) if len(v) else None for _, v in numbers.values()], "highs": [int(v.max()) if len(v) else None for _, v in numbers.values()],
        }

    def blocks(table: pa.Table, qid: np.ndarray) -> Iterator[pa.RecordBatch]:
        start = np.flatnonzero(np.concatenate([[True], qid[1:] != qid[:-1]]))
        ends = np.append(start, len(qid))
        for a in range(0, len(start), BLOCK):
            some = start[a : a + BLOCK]
            low, high = int(some[0]), int(ends[min(a + BLOCK, len(start))])
            own = some - low
            entry = np.repeat(np.arange(len(own)), np.diff(np.append(own, high - low)))
            row = block(table.slice(low, high - low), own, entry, qid[low:high])
            yield pa.RecordBatch.from_pydict({k: pa.array([v], kind) for (k, v), kind in zip(row.items(), _TYPES)})

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        n = 0
        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n < 8 * BLOCK:
                continue
            table = pa.Table.from_batches(held)
            qid = table.column("qid").to_numpy()
            cut = int(np.searchsorted(qid, qid[-1]))  # the last entry may go on in the next batch
            if cut:
                yield from blocks(table.slice(0, cut), qid[:cut])
            held = table.slice(cut).to_batches()
            n = len(qid) - cut if cut else 0  # an entry of very many rows is looked at as seldom as it doubles
        if held and sum(b.num_rows for b in held):
            table = pa.Table.from_batches(held)
            yield from blocks(table, table.column("qid").to_numpy())

    met = rows.table.where(F.col("qid").isNotNull()).repartition("qid").sortWithinPartitions("qid")
    return written(met.mapInArrow(run, _CODED), "coded")


_TYPES = [*[pa.binary()] * 5, pa.list_(pa.string()), pa.list_(pa.string()), pa.list_(pa.int64()), pa.list_(pa.string()), pa.list_(pa.binary()), pa.list_(pa.binary()), pa.list_(pa.int64()), pa.list_(pa.int64())]


def edges(table: DataFrame, pinned: dict[str, tuple[int, int]] | None) -> dict[str, tuple[int, int]]:
    """Bounds of each numeric feature: one row each, from those of the blocks."""
    if pinned is not None:
        return pinned
    each = table.select(F.explode(F.arrays_zip("numbers", "lows", "highs")).alias("x"))
    return {r["f"]: (r["lo"], r["hi"]) for r in each.groupBy(F.col("x.numbers").alias("f")).agg(F.min("x.lows").alias("lo"), F.max("x.highs").alias("hi")).collect()}


def _bucketed(values: np.ndarray, low: int, high: int, buckets: int) -> np.ndarray:
    """What numeric.bucket() gives."""
    if high == low:
        return np.zeros(len(values), np.int64)
    whole = (np.clip(values, low, high) - low) * buckets
    return ((whole - whole % (high - low)) / (high - low)).astype(np.int64)


def _numbers(row: dict, bounds: dict, buckets: int) -> Iterator[tuple[str, np.ndarray, np.ndarray]]:
    for name, at, values in zip(row["numbers"], row["at"], row["values"]):
        own = np.frombuffer(values, np.int64)
        if len(own):
            yield name, np.frombuffer(at, np.int32), _bucketed(own, *bounds[name], buckets)


def frequencies(table: DataFrame, bounds: dict, buckets: int) -> DataFrame:
    """(feature, token, freq) of the whole log."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for row in batch.to_pylist():
                for name, _, b in _numbers(row, bounds, buckets):
                    total[name] = total.get(name, np.zeros(buckets + 1, np.int64)) + np.bincount(b, minlength=buckets + 1)
        for name, counts in total.items():
            hit = np.flatnonzero(counts)
            yield pa.RecordBatch.from_pydict({"feature": pa.array([name] * len(hit), pa.string()), "token": pa.array([str(b) for b in hit], pa.string()), "freq": pa.array(counts[hit])})

    words = table.select(F.explode(F.arrays_zip("features", "words", "counts")).alias("x")).select(F.col("x.features").alias("feature"), F.col("x.words").alias("token"), F.col("x.counts").alias("freq"))
    numbers = table.select("numbers", "at", "values").mapInArrow(run, "feature string, token string, freq long")
    return words.unionByName(numbers).groupBy("feature", "token").agg(F.sum("freq").alias("freq"))


def packed(table: DataFrame, dom: DataFrame, bounds: dict, buckets: int) -> Blocks:
    """Blocks with the domain's ids, sorted by id within an entry; entries without tokens are left out, as no row of tokens() is theirs. The domain is sent around."""
    shared = table.sparkSession.sparkContext.broadcast(dom.select("tid", "feature", "token").toArrow().combine_chunks())

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by: dict[str, tuple[np.ndarray, pa.Array]] = {}
        known = shared.value
        for name in pc.unique(known.column("feature")).to_pylist():
            own = known.filter(pc.equal(known.column("feature"), name))
            by[name] = own.column("tid").to_numpy(), own.column("token").combine_chunks()
        places = {name: {t: int(i) for t, i in zip(tokens.to_pylist(), tids)} for name, (tids, tokens) in by.items()}
        number = {}
        for name in bounds:
            number[name] = np.full(buckets + 1, -1, np.int32)
            for t, i in places.get(name, {}).items():
                number[name][int(t)] = i
        for batch in batches:
            for row in batch.to_pylist():
                ids = np.array([places[f][w] for f, w in zip(row["features"], row["words"])], np.int32)
                size = np.frombuffer(row["size"], np.int32)
                qid, n = np.frombuffer(row["qid"], np.int64), len(size)
                who, tids, mults = [np.repeat(np.arange(n), size)], [ids[np.frombuffer(row["codes"], np.int32)]], [np.frombuffer(row["mults"], np.int32)]
                for name, at, b in _numbers(row, bounds, buckets):
                    who.append(at)
                    tids.append(number[name][b])
                    mults.append(np.ones(len(at), np.int32))
                who, tids, mults = np.concatenate(who).astype(np.int64), np.concatenate(tids), np.concatenate(mults)
                order = np.argsort((who << 32) + tids, kind="stable")
                size = np.bincount(who, minlength=n).astype(np.int64)
                some = np.flatnonzero(size)
                entries = Entries(qid[some], np.frombuffer(row["cost"], np.float64)[some], np.zeros(len(some)), size[some], tids[order], mults[order])
                yield from (batch_of([r]) for r in rows_of(entries))

    return Blocks(written(table.select("qid", "cost", "size", "codes", "mults", "features", "words", "numbers", "at", "values").mapInArrow(run, SCHEMA), "blocks"))
