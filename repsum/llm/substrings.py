"""Exact removal of byte strings that occur more than once, by suffix arrays over aligned contexts.

A string of ``length`` bytes that starts at two places must be found wherever its copies are.
Every window of that length owns one *anchor*: the position, among its first ``spread``, with the
smallest hash of the ``gram`` bytes that start there (the leftmost on a tie). The choice depends on
the window's bytes alone, so equal windows have equal anchors at equal offsets, and the ``length -
spread + 1`` bytes that follow an anchor are shared by all copies of all its windows: their hash is
the key that brings copies together. Keys that occur once are gone after one aggregation of counts.

The bytes that an anchor's windows cover are its context. Equal contexts of a key collapse to one
row, and all their windows are repeated. Different contexts of a key stand below each other,
aligned at the anchor; neighbouring columns that tell the same rows apart are one symbol. A suffix
array of those rows, built by linear grouping (see suffixes.py), brings equal starts together, and
a window is repeated if and only if a neighbour shares as many symbols as it spans. Only the
starts of repeated windows travel back to the documents.

Keys of which very many different contexts exist (a passage shorter than ``length`` that many
texts have) are dealt again: under another hash every window of these contexts gets another
anchor, and the bytes behind it and the distance of the two anchors make a finer key, whose
contexts are treated as those of any key. Windows that stay crowded are dealt again, and after
``DEPTH`` times by their own bytes, so no task ever holds more than ``crowd`` contexts of a key.
Rows are told apart by 64 bits of their text, contexts by 128 (key and context hash).

Edge cases: null and empty texts have no bytes; texts shorter than ``length`` lose nothing;
repeated rows are copies of each other; rows that share a doc_id but not a text are told apart by
a hash of the text; a null doc_id is kept; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, functions as F

from repsum.llm.arrow import slices
from repsum.llm.suffixes import common_prefixes, suffix_array
from repsum.plans.scratch import materialise

LENGTH = 200
SPREAD = 160
GRAM = 16
#: Different contexts of a key that one task sorts, and how often more of them are dealt by other anchors.
CROWD = 1 << 10
DEPTH = 6
#: Windows handled at once in one text, and symbols sorted at once in a task.
STRETCH = 1 << 19
SYMBOLS = 1 << 17


def gram_hashes(raw: np.ndarray, gram: int = GRAM, salt: int = 0) -> np.ndarray:
    """A 64-bit hash of the ``gram`` (a power of two) bytes from each position; another one for each salt."""
    h = raw.astype(np.uint64) + np.uint64(1)
    step, odd = 1, 0x9E3779B97F4A7C15
    while step < gram:
        h = h[:-step] * np.uint64(odd) + h[step:]
        odd = (odd * odd + 2 * step) % (1 << 64)
        step *= 2
    h ^= np.uint64(salt * 0x9E3779B97F4A7C15 % (1 << 64))
    h ^= h >> np.uint64(31)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return h


def anchors(raw: np.ndarray, length: int = LENGTH, spread: int = SPREAD, gram: int = GRAM, salt: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(anchor position, first window start, number of windows) of a text of at least ``length`` bytes."""
    last = len(raw) - length + 1  # windows start at 0 .. last - 1
    where, first = [], []
    low = np.uint64((1 << 20) - 1)
    for begin in range(0, last, STRETCH):
        end = min(begin + STRETCH, last)
        h = gram_hashes(raw[begin : end + spread - 1 + gram - 1], gram, salt)
        least = (h & ~low) | np.arange(len(h), dtype=np.uint64)
        width = 1
        while width < spread:
            step = min(width, spread - width)
            least = np.minimum(least[:-step], least[step:])
            width += step
        at = (least & low).astype(np.int64) + begin
        edge = np.flatnonzero(np.diff(at, prepend=-1))
        where.append(at[edge])
        first.append(edge + begin)
    where, first = np.concatenate(where), np.concatenate(first)
    if len(where) > 1:  # an anchor that goes on over a stretch's end
        keep = np.append(True, where[1:] != where[:-1])
        where, first = where[keep], first[keep]
    return where, first, np.diff(np.append(first, last))


def anchor_rows(docs: DataFrame, length: int = LENGTH, spread: int = SPREAD) -> DataFrame:
    """(key, context, doc_id, mark, place) of every anchor; mark is a hash of the text, see pack() for place."""
    tail = length - spread + 1

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key_of, context_of = xxhash.xxh64_intdigest, xxhash.xxh3_64_intdigest
        for whole in batches:
            for part in slices(whole, "raw"):
                docs_out, marks, keys, contexts, places = [], [], [], [], []
                for doc, raw in zip(part.column("doc_id").to_pylist(), part.column("raw").to_pylist()):
                    if raw is None or len(raw) < length:
                        continue
                    at, first, count = anchors(np.frombuffer(raw, np.uint8), length, spread)
                    begin, end = first.tolist(), (first + count - 1 + length).tolist()
                    keys += [key_of(raw[p : p + tail]) for p in at.tolist()]
                    # offsets are part of a context, so that equal contexts have equal windows
                    contexts += [context_of(raw[b:e], p - b) for b, e, p in zip(begin, end, at.tolist())]
                    places.append(pack(first, count, at - first))
                    docs_out += [doc] * len(begin)
                    marks += [text_mark(raw)] * len(begin)
                if docs_out:
                    yield pa.RecordBatch.from_arrays([pa.array(np.array(keys, np.uint64).view(np.int64)), pa.array(np.array(contexts, np.uint64).view(np.int64)), pa.array(docs_out, pa.int64()), pa.array(marks, pa.int64()), pa.array(np.concatenate(places))], names=["key", "context", "doc_id", "mark", "place"])

    return docs.mapInArrow(run, "key long, context long, doc_id long, mark long, place long")


def text_mark(raw: bytes) -> int:
    """64 bits of a text, as a signed number."""
    return xxhash.xxh64_intdigest(raw, 7) - (1 << 63)


def pack(first, windows, offset):
    """One number of a first window (32 bits), a number of windows (8) and the anchor's offset in the first (8)."""
    return (first << 32) | (windows << 24) | (offset << 16)


def unpack(place: int) -> tuple[int, int, int]:
    """(first window, windows, offset of the anchor in the first window)."""
    return place >> 32, (place >> 24) & 0xFF, (place >> 16) & 0xFF


def _shared(parts: list[bytes]) -> np.ndarray:
    """Longest prefix that each of several strings shares with any other."""
    if len(parts) == 2:
        n = min(map(len, parts))
        x, y = (np.frombuffer(p, np.uint8, n) for p in parts)
        off = np.flatnonzero(x != y)
        return np.full(2, int(off[0]) if len(off) else n)
    order = sorted(range(len(parts)), key=parts.__getitem__)
    width = max(map(len, parts)) + 1
    cells = np.broadcast_to(-1 - np.arange(len(parts), dtype=np.int32)[:, None], (len(parts), width)).copy()  # ends equal nothing
    for r, i in enumerate(order):
        cells[r, : len(parts[i])] = np.frombuffer(parts[i], np.uint8)
    same = (cells[1:] != cells[:-1]).argmax(axis=1)
    out = np.zeros(len(parts), np.int64)
    out[order] = np.maximum(np.append(same, 0), np.append(0, same))
    return out


def _labels(rows: np.ndarray) -> np.ndarray:
    """For each column, the number of the first row with the same value."""
    m, width = rows.shape
    if m <= 24:
        return np.argmax(rows[None, :, :] == rows[:, None, :], axis=1)
    out = np.empty((m, width), np.int64)
    for c in range(width):
        _, first, inverse = np.unique(rows[:, c], return_index=True, return_inverse=True)
        out[:, c] = first[inverse]
    return out


class Aligned:
    """The different contexts of one key below each other, as rows of symbols.

    A row that shares ``l`` bytes before and ``r`` bytes from the anchor with other rows, at most,
    can only repeat windows inside these; the rest of it is cut off, and rows without such a
    window are left out. Partners of a repeated window share it, so they are never left out.
    """

    def __init__(self, contexts: list[tuple[bytes, int, int]], length: int) -> None:
        """contexts: (bytes, offset of the anchor in the first window, windows)."""
        self.size, self.length = len(contexts), length
        right = _shared([raw[offset:] for raw, offset, _ in contexts])
        left = _shared([raw[:offset][::-1] for raw, offset, _ in contexts])
        offsets = np.array([o for _, o, _ in contexts])
        counts = np.array([c for *_, c in contexts])
        most = np.minimum(offsets, left)  # window offsets between least and most may be repeated
        least = np.maximum(offsets - counts + 1, length - right)
        self.alive = np.flatnonzero(most >= least)
        self.rows: list[list[int]] = []
        self.alphabet = 0
        if len(self.alive) < 2:
            self.alive = self.alive[:0]
            return
        self.offsets, self.most, self.least = offsets[self.alive], most[self.alive], least[self.alive]
        zero = int(self.most.max())  # the anchor's column
        width = zero + length - int(self.least.min())
        m = len(self.alive)
        cells = np.broadcast_to(256 + np.arange(m, dtype=np.int32)[:, None], (m, width)).copy()  # what is cut off equals nothing
        for r, i in enumerate(self.alive):
            raw, offset, _ = contexts[i]
            piece = raw[offset - self.most[r] : offset + length - self.least[r]]
            cells[r, zero - self.most[r] : zero - self.most[r] + len(piece)] = np.frombuffer(piece, np.uint8)
        labels = _labels(cells)
        fresh = np.append(True, (labels[:, 1:] != labels[:, :-1]).any(axis=0))
        column = np.cumsum(fresh) - 1
        symbols = labels[:, fresh] + (np.arange(fresh.sum()) * m)[None, :]
        self.alphabet = int(fresh.sum()) * m
        self.spans = []
        for r in range(m):
            first, last = column[zero - self.most[r]], column[zero + length - self.least[r] - 1]
            self.rows.append(symbols[r, first : last + 1].tolist())
            begin = zero - np.arange(self.most[r], self.least[r] - 1, -1)  # columns where windows start
            self.spans.append((column[begin] - first, column[begin + length - 1] - column[begin] + 1))

    def repeated(self, longest: np.ndarray, at: list[int]) -> list[list[int]]:
        """Per context: numbers of its repeated windows; ``longest`` is each symbol's longest match with another row, ``at`` where rows begin."""
        out: list[list[int]] = [[] for _ in range(self.size)]
        for r, i in enumerate(self.alive.tolist()):
            start, need = self.spans[r]
            out[i] = (np.flatnonzero(longest[at[r] + start] >= need) + self.offsets[r] - self.most[r]).tolist()
        return out


def resolve(groups: list[Aligned]) -> list[list[list[int]]]:
    """Repeated windows of several keys by one suffix array; keys have alphabets of their own."""
    text: list[int] = []
    base, at = 0, []
    stop = sum(g.alphabet for g in groups)  # symbols that end a row, each once
    for g in groups:
        begins = []
        for row in g.rows:
            begins.append(len(text))
            text += [x + base for x in row]
            text.append(stop)
            stop += 1
        at.append(begins)
        base += g.alphabet
    order = suffix_array(text)
    same = common_prefixes(text, order)
    longest = np.zeros(len(text), np.int64)
    longest[order] = np.maximum(same, np.append(same[1:], 0)) if text else 0
    return [g.repeated(longest, begins) for g, begins in zip(groups, at)]


def _runs(numbers: list[int]) -> list[tuple[int, int]]:
    n = np.array(numbers, np.int64)
    cut = np.flatnonzero(np.diff(n) > 1)
    return list(zip(n[np.append(0, cut + 1)].tolist(), (n[np.append(cut, len(n) - 1)] + 1).tolist()))


_RUNS = "array<struct<begin:int,end:int>>"


def sort_contexts(contexts: DataFrame, length: int = LENGTH) -> DataFrame:
    """(key, context, runs) of repeated windows from (key, context, place, bytes)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: list[tuple[int, list[int], Aligned]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            keys, names, runs = [], [], []
            for (key, own, _), found in zip(waiting, resolve([g for *_, g in waiting])):
                for context, numbers in zip(own, found):
                    if numbers:
                        keys.append(key)
                        names.append(context)
                        runs.append([{"begin": a, "end": b} for a, b in _runs(numbers)])
            waiting.clear()
            return pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(names, pa.int64()), pa.array(runs, pa.list_(pa.struct([("begin", pa.int32()), ("end", pa.int32())])))], names=["key", "context", "runs"])

        def groups() -> Iterator[tuple[int, list[tuple]]]:
            key, rows = None, []
            for batch in batches:
                for k, *rest in zip(*(c.to_pylist() for c in (batch.column(n) for n in ("key", "context", "place", "bytes")))):
                    if k != key and rows:
                        yield key, rows
                        rows = []
                    key = k
                    rows.append(rest)
            if rows:
                yield key, rows

        for key, rows in groups():
            shape = [unpack(place) for _, place, _ in rows]
            group = Aligned([(raw, offset, count) for (_, _, raw), (_, count, offset) in zip(rows, shape)], length)
            if not len(group.alive):
                continue
            waiting.append((key, [c for c, *_ in rows], group))
            size += sum(map(len, group.rows))
            if size >= SYMBOLS:
                yield flush()
                size = 0
        if waiting:
            yield flush()

    return contexts.repartition("key").sortWithinPartitions("key", "context").mapInArrow(run, f"key long, context long, runs {_RUNS}")


_BACK = "okey long, ocontext long, base int, key long, context long, place long, bytes binary"


def deal_again(contexts: DataFrame, length: int, spread: int, depth: int, last: bool) -> DataFrame:
    """Parts of contexts under finer keys: (okey, ocontext, base, key, context, place, bytes).

    ``base`` is a part's first window in its context. Keys come from anchors under another hash,
    and the ``last`` time from whole windows, whose parts are equal wherever they meet.
    """
    tail = length - spread + 1

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key_of, context_of = xxhash.xxh64_intdigest, xxhash.xxh3_64_intdigest
        for batch in batches:
            out: list[list] = [[] for _ in range(7)]
            for key, context, place, raw in zip(*(batch.column(n).to_pylist() for n in ("key", "context", "place", "bytes"))):
                _, count, offset = unpack(place)
                if last:
                    at = first = np.arange(count)
                    many = np.ones(count, np.int64)
                else:
                    at, first, many = anchors(np.frombuffer(raw, np.uint8), length, spread, salt=depth)
                for p, f, n in zip(at.tolist(), first.tolist(), many.tolist()):
                    part = raw[f : f + n - 1 + length]
                    named = part if last else raw[p : p + tail] + (p - offset).to_bytes(4, "little", signed=True)
                    row = (key, context, f, key_of(named, key % (1 << 64)) - (1 << 63), context_of(part, p - f) - (1 << 63), pack(0, n, p - f), part)
                    for column, value in zip(out, row):
                        column.append(value)
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out, kinds)], names=["okey", "ocontext", "base", "key", "context", "place", "bytes"])

    return contexts.select("key", "context", "place", "bytes").mapInArrow(run, _BACK)


def settle(contexts: DataFrame, length: int, spread: int, crowd: int, depth: int = 0) -> DataFrame:
    """(key, context, runs) of repeated windows of different contexts (key, context, place, bytes, m), m of each key."""
    found = sort_contexts(contexts.where(F.col("m") <= crowd).drop("m"), length)
    hot = contexts.where(F.col("m") > crowd)
    if depth > DEPTH or hot.isEmpty():
        return found
    parts = materialise(deal_again(hot, length, spread, depth + 1, depth == DEPTH), "parts")
    distinct = materialise(parts.groupBy("key", "context").agg(F.count("*").alias("n"), F.any_value("place").alias("place"), F.any_value("bytes").alias("bytes")), "part-contexts")
    several = distinct.groupBy("key").agg(F.count("*").alias("m")).where("m > 1")
    finer = settle(materialise(distinct.join(several, "key").select("key", "context", "place", "bytes", "m"), "finer"), length, spread, crowd, depth + 1)
    once = distinct.where("n = 1").select("key", "context")
    runs = finer.join(once, ["key", "context"], "left_semi").unionByName(distinct.where("n > 1").select("key", "context", _every().alias("runs")))
    moved = F.transform("runs", lambda r: F.struct((r["begin"] + F.col("base")).alias("begin"), (r["end"] + F.col("base")).alias("end")))
    back = parts.select("okey", "ocontext", "base", "key", "context").join(runs, ["key", "context"]).select("okey", "ocontext", moved.alias("runs"))
    per = back.groupBy("okey", "ocontext").agg(F.array_sort(F.flatten(F.collect_list("runs"))).alias("runs"))  # at most ``spread`` of a context
    return found.unionByName(per.select(F.col("okey").alias("key"), F.col("ocontext").alias("context"), "runs"))


def _every() -> Column:
    """All windows of a place as one run."""
    return F.array(F.struct(F.lit(0).alias("begin"), F.expr("cast(shiftright(place, 24) & 255 as int)").alias("end")))


def repeated_windows(raw: DataFrame, length: int = LENGTH, spread: int = SPREAD, crowd: int = CROWD) -> DataFrame:
    """(doc_id, mark, begin, end): starts begin .. end - 1 of repeated windows; mark is the text hash of a place."""
    rows = anchor_rows(raw, length, spread)
    # written, so that the join below has shuffles of its own, whose crowded keys can be split
    keys = materialise(rows.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"), "repeated-keys")
    dup = materialise(rows.join(keys, "key"), "repeated-anchors")
    distinct = dup.groupBy("key", "context").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "mark", "place")).alias("one"))
    distinct = materialise(distinct.select("key", "context", "n", "one.doc_id", "one.mark", "one.place"), "contexts")
    several = materialise(distinct.groupBy("key").agg(F.count("*").alias("m")).where("m > 1"), "several")
    asked = distinct.join(several, "key").select("key", "context", "doc_id", "mark", "place", "m")
    per_doc = asked.groupBy("doc_id", "mark").agg(F.collect_list(F.struct("key", "context", "place", "m")).alias("asked"))  # bounded by the text

    def cut(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for part in slices(whole, "raw"):
                out: list[list] = [[], [], [], [], []]
                for text, mark, asked in zip(*(part.column(n).to_pylist() for n in ("raw", "mark", "asked"))):
                    if text_mark(text) != mark:
                        continue  # another text under the same doc_id
                    for a in asked:
                        first, count, offset = unpack(a["place"])
                        piece = text[first : first + count - 1 + length]
                        if xxhash.xxh3_64_intdigest(piece, offset) != a["context"] % (1 << 64):
                            continue
                        for column, value in zip(out, (a["key"], a["context"], a["place"], piece, a["m"])):
                            column.append(value)
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out, (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64()))], names=["key", "context", "place", "bytes", "m"])

    wide = raw.join(per_doc, raw["doc_id"].eqNullSafe(per_doc["doc_id"])).select("raw", "mark", "asked")
    contexts = wide.mapInArrow(cut, "key long, context long, place long, bytes binary, m long")
    # rows equal in doc_id and text bring a context more than once, which a crowded key's parts must not count
    crowded = not several.where(F.col("m") > crowd).isEmpty()
    found = settle(materialise(contexts.dropDuplicates(["key", "context"]), "context-bytes"), length, spread, crowd) if crowded else sort_contexts(contexts.drop("m"), length)
    single = distinct.where("n = 1").select("key", "context")
    copied = distinct.where("n > 1").select("key", "context", _every().alias("runs"))
    runs = found.join(single, ["key", "context"], "left_semi").unionByName(copied.select("key", "context", "runs"))
    hit = dup.join(runs, ["key", "context"]).select("doc_id", "mark", F.shiftright("place", 32).alias("first"), F.explode("runs").alias("r"))
    return hit.select("doc_id", "mark", (F.col("first") + F.col("r.begin")).alias("begin"), (F.col("first") + F.col("r.end")).alias("end"))


def remove_repeats(docs: DataFrame, length: int = LENGTH, spread: int = SPREAD, crowd: int = CROWD, id_col: str = "doc_id", text_col: str = "text", with_bytes: bool = False) -> DataFrame:
    """(doc_id, n_bytes, n_removed, spans, kept_sha256[, kept]) of every row; spans are the removed byte runs."""
    raw = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("raw"))
    found = repeated_windows(raw, length, spread, crowd)
    per_doc = found.groupBy("doc_id", "mark").agg(F.collect_set(F.struct("begin", "end")).alias("starts"))  # bounded by the text
    per_id = per_doc.groupBy("doc_id").agg(F.collect_list(F.struct("mark", "starts")).alias("marks"))
    per_id = per_id.select(F.col("doc_id").alias("found_id"), "marks")
    schema = f"doc_id long, n_bytes long, n_removed long, spans array<struct<begin:long,end:long>>, kept_sha256 string" + ", kept binary" * with_bytes

    def cut(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        span = pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))
        for whole in batches:
            for part in slices(whole, "raw"):
                out: list[list] = [[] for _ in range(5 + with_bytes)]
                for doc, text, marks in zip(*(part.column(n).to_pylist() for n in ("doc_id", "raw", "marks"))):
                    spans: list[tuple[int, int]] = []
                    if marks:
                        own = text_mark(text)
                        starts = sorted((s["begin"], s["end"] - 1 + length) for m in marks if m["mark"] == own for s in m["starts"])
                        for a, b in starts:
                            if spans and a <= spans[-1][1]:
                                spans[-1] = spans[-1][0], max(b, spans[-1][1])
                            else:
                                spans.append((a, b))
                    at, kept = 0, []
                    for a, b in spans:
                        kept.append(text[at:a])
                        at = b
                    kept.append(text[at:])
                    rest = b"".join(kept)
                    row = [doc, len(text), len(text) - len(rest), [{"begin": a, "end": b} for a, b in spans], hashlib.sha256(rest).hexdigest()] + [rest] * with_bytes
                    for column, value in zip(out, row):
                        column.append(value)
                kinds = [pa.int64(), pa.int64(), pa.int64(), span, pa.string(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out, kinds)], names=["doc_id", "n_bytes", "n_removed", "spans", "kept_sha256", "kept"][: 5 + with_bytes])

    joined = raw.join(per_id, raw["doc_id"].eqNullSafe(per_id["found_id"]), "left").select("doc_id", "raw", "marks")
    return joined.mapInArrow(cut, schema)
