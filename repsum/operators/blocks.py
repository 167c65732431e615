"""Entries in blocks: a row of a table holds thousands of entries as flat arrays in binary columns.

A pass over blocks hands whole arrays to the workers instead of one list per entry, so it takes
little more than the arithmetic. ``hash`` is there if asked for, see ``Blocks.hashed()``.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from repsum.plans.scratch import materialise

#: Entries and tokens of a block at most.
BLOCK, BLOCK_TOKENS = 4096, 1 << 18
KINDS = {"qid": np.int64, "cost": np.float64, "size": np.int32, "tids": np.int32, "mults": np.int32}
#: Small numbers are kept in fewer bytes; how many, their total length says.
NARROW = {"size": [np.uint8, np.uint16], "tids": [np.uint16], "mults": [np.uint8]}
WIDTHS = {1: np.uint8, 2: np.uint16, 4: np.int32}
SCHEMA = ", ".join(f"{name} binary" for name in KINDS)
#: Bytes of a row group of a table of blocks: what a reader holds at once.
ROW_GROUP = 16 << 20


@dataclass
class Entries:
    """Entries end to end in a few arrays, whatever their number; ``size`` tokens each."""

    qid: np.ndarray
    cost: np.ndarray
    gain: np.ndarray
    size: np.ndarray
    tids: np.ndarray
    mults: np.ndarray

    @staticmethod
    def of(picks: list) -> Entries:
        n, ends = len(picks), lambda parts: np.concatenate(parts) if parts else np.zeros(0, np.int64)
        column = lambda name, kind: np.fromiter((getattr(p, name) for p in picks), kind, n)
        size = np.fromiter((len(p.tids) for p in picks), np.int64, n)
        return Entries(column("qid", np.int64), column("cost", np.float64), column("gain", np.float64), size, ends([p.tids for p in picks]), ends([p.mults for p in picks]))

    @staticmethod
    def of_table(table: pa.Table) -> Entries:
        """Of a table's columns qid, cost, tids, mults and, if there, gain; tokens keep their width."""
        flat = lambda name: np.concatenate([np.zeros(0, np.int32), *(_flat(c) for c in table.column(name).chunks)])
        size = np.concatenate([np.zeros(0, np.int64), *(_sizes(c) for c in table.column("tids").chunks)])
        gain = table.column("gain").to_numpy() if "gain" in table.column_names else np.zeros(table.num_rows)
        return Entries(table.column("qid").to_numpy(), table.column("cost").to_numpy(), gain, size, flat("tids"), flat("mults"))

    @staticmethod
    def joined(parts: list[Entries]) -> Entries:
        return Entries(*(np.concatenate([getattr(p, name) for p in parts]) for name in ("qid", "cost", "gain", "size", "tids", "mults")))

    def __len__(self) -> int:
        return len(self.qid)

    def starts(self) -> np.ndarray:
        return np.cumsum(self.size, dtype=np.int64) - self.size

    def take(self, some: np.ndarray) -> Entries:
        size = self.size[some].astype(np.int64)
        begin = np.cumsum(size) - size
        at = np.repeat(self.starts()[some] - begin, size) + np.arange(size.sum())
        return Entries(self.qid[some], self.cost[some], self.gain[some], size, self.tids[at], self.mults[at])


def _flat(lists: pa.Array) -> np.ndarray:
    """Values of lists, or of binaries of whole int32s, end to end."""
    if not pa.types.is_binary(lists.type) and not pa.types.is_large_binary(lists.type):
        return lists.flatten().to_numpy(zero_copy_only=False)
    if not len(lists):
        return np.zeros(0, np.int32)
    ends = _offsets(lists)
    return np.frombuffer(lists.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]].view(np.int32) if ends[-1] > ends[0] else np.zeros(0, np.int32)


def _offsets(lists: pa.Array) -> np.ndarray:
    if not pa.types.is_binary(lists.type) and not pa.types.is_large_binary(lists.type):
        return lists.offsets.to_numpy()
    kind = np.int64 if pa.types.is_large_binary(lists.type) else np.int32
    return np.frombuffer(lists.buffers()[1], kind)[lists.offset : lists.offset + len(lists) + 1]


def _sizes(lists: pa.Array) -> np.ndarray:
    unit = 1 if pa.types.is_list(lists.type) or pa.types.is_large_list(lists.type) else 4
    return np.diff(_offsets(lists)).astype(np.int64) // unit


def of_batch(batch: pa.RecordBatch) -> Iterator[tuple[Entries, np.ndarray | None]]:
    """(entries, their hashes) of a batch of blocks, or of rows with lists."""
    if pa.types.is_binary(batch.schema.field("qid").type):
        for i in range(batch.num_rows):
            cell = lambda name, kind: np.frombuffer(batch.column(name)[i].as_buffer(), kind)
            own, n = {name: cell(name, KINDS[name]) for name in ("qid", "cost")}, batch.column("qid")[i].as_buffer().size // 8
            for name in ("size", "tids", "mults"):
                held = batch.column(name)[i].as_buffer()
                own[name] = np.frombuffer(held, WIDTHS[held.size // n if n else 4])
                n = int(own["size"].sum())
            yield Entries(gain=np.zeros(len(own["qid"])), **own), cell("hash", np.uint32) if "hash" in batch.schema.names else None
    elif batch.num_rows:
        yield Entries.of_table(pa.Table.from_batches([batch])), None


def rows_of(entries: Entries) -> Iterator[dict]:
    """Blocks of entries, as the values of rows."""
    upto, a = np.cumsum(entries.size, dtype=np.int64), 0
    while a < len(entries):
        done = int(upto[a - 1]) if a else 0
        b = max(a + 1, min(a + BLOCK, int(np.searchsorted(upto, done + BLOCK_TOKENS, "right"))))
        span = {"tids": slice(done, int(upto[b - 1])), "mults": slice(done, int(upto[b - 1]))}
        yield {name: _narrow(name, getattr(entries, name)[span.get(name, slice(a, b))]).tobytes() for name in KINDS}
        a = b


def _narrow(name: str, values: np.ndarray) -> np.ndarray:
    kinds = [k for k in NARROW.get(name, []) if not len(values) or values.min() >= 0 and values.max() <= np.iinfo(k).max]
    return np.ascontiguousarray(values, kinds[0] if kinds else KINDS[name])


def batch_of(rows: list[dict]) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({name: pa.array([r[name] for r in rows], pa.binary()) for name in rows[0]})


def hash_of(qids: np.ndarray, seed: int = 42) -> np.ndarray:
    """The 32 bits of which partitioned.part_of() takes the remainder."""
    text = f"{seed}|%d".encode()
    return np.frombuffer(b"".join([hashlib.md5(text % q).digest()[:4] for q in qids.tolist()]), ">u4").astype(np.uint32)


@dataclass
class Blocks:
    table: DataFrame
    _hashed: Blocks | None = None

    @property
    def sparkSession(self) -> SparkSession:
        return self.table.sparkSession

    @staticmethod
    def of(vectors: DataFrame) -> Blocks:
        """Of rows (qid, cost, tids, mults), written once."""

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: list[Entries] = []
            for batch in batches:
                held += [e for e, _ in of_batch(batch)]
                if sum(map(len, held)) >= BLOCK or sum(len(e.tids) for e in held) >= BLOCK_TOKENS:
                    yield from (batch_of([r]) for r in rows_of(Entries.joined(held)))
                    held = []
            if held:
                yield from (batch_of([r]) for r in rows_of(Entries.joined(held)))

        return Blocks(written(vectors.select("qid", "cost", "tids", "mults").mapInArrow(run, SCHEMA), "blocks"))

    def rows(self) -> DataFrame:
        """(qid, cost, tids, mults)."""

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for e, _ in of_batch(batch):
                    ends = pa.array(np.append(e.starts(), len(e.tids)).astype(np.int32))
                    lists = (pa.ListArray.from_arrays(ends, pa.array(x.astype(np.int32))) for x in (e.tids, e.mults))
                    yield pa.RecordBatch.from_arrays([pa.array(e.qid), pa.array(e.cost, from_pandas=True), *lists], ["qid", "cost", "tids", "mults"])

        return self.table.mapInArrow(run, "qid long, cost double, tids array<int>, mults array<int>")

    def total_cost(self) -> float:
        """The sum of all costs; those that are no number count nothing."""

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = sum(float(np.nansum(e.cost)) for batch in batches for e, _ in of_batch(batch))
            yield pa.RecordBatch.from_pydict({"cost": pa.array([total], pa.float64())})

        return float(self.table.mapInArrow(run, "cost double").agg({"cost": "sum"}).head()[0] or 0.0)

    def hashed(self) -> Blocks:
        """The same with the hash that decides on an entry's part, written once."""
        if self._hashed is not None or "hash" in self.table.columns:
            return self._hashed or self

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                more = [hash_of(e.qid).tobytes() for e, _ in of_batch(batch)]
                yield batch.append_column("hash", pa.array(more, pa.binary()))

        self._hashed = Blocks(written(self.table.mapInArrow(run, f"{SCHEMA}, hash binary"), "hashed"))
        return self._hashed

    def counts(self, parts: int, size: int | None = None) -> DataFrame:
        """(part, n, t): entries and tokens of each part; with the domain's ``size`` (part, tid, n), how often a part has each of its tokens."""

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros((parts, 2 if size is None else size), np.int64)
            for batch in batches:
                for e, hashes in of_batch(batch):
                    part = hashes.astype(np.int64) % parts
                    if size is None:
                        total[:, 0] += np.bincount(part, minlength=parts)
                        total[:, 1] += np.bincount(part, weights=e.size, minlength=parts).astype(np.int64)
                    else:
                        total += np.bincount(np.repeat(part, e.size) * size + e.tids, weights=e.mults, minlength=parts * size).astype(np.int64).reshape(parts, size)
            if size is None:
                some = np.flatnonzero(total[:, 0])
                yield pa.RecordBatch.from_pydict({"part": pa.array(some, pa.int32()), "n": total[some, 0], "t": total[some, 1]})
            else:
                part, tid = np.nonzero(total)
                yield pa.RecordBatch.from_pydict({"part": pa.array(part, pa.int32()), "tid": pa.array(tid, pa.int32()), "n": total[part, tid]})

        if size is None:
            return self.hashed().table.mapInArrow(run, "part int, n long, t long").groupBy("part").agg({"n": "sum", "t": "sum"}).toDF("part", "n", "t")
        return self.hashed().table.mapInArrow(run, "part int, tid int, n long").groupBy("part", "tid").agg({"n": "sum"}).toDF("part", "tid", "n")


def written(df: DataFrame, name: str) -> DataFrame:
    return materialise(df, name, {"parquet.block.size": ROW_GROUP})
