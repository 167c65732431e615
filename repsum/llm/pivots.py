"""SimHash fingerprints and links by pivot distance tables.

A fingerprint is the bitwise majority of the XXH64 hashes of a text's word shingles. Equal
fingerprints collapse to one row first, so copies never meet each other. Two fingerprints
within radius r agree on at least (blocks - r) of their bit blocks, so rows are dealt by each
choice of two of five blocks, a key of 25 or 26 bits; no pair within 3 bits can miss every
choice. Each fingerprint brings its row of the pivot table, its Hamming distances to reference
fingerprints, computed once before the rows are dealt. By the triangle inequality two fingerprints whose distances to some pivot
differ by more than r cannot be linked: such pairs are discarded by their largest coordinate
difference, survivors are verified bit by bit, and a key emits a spanning forest of its links
only. A key with very many different fingerprints is cut into pieces, and every pair of
pieces becomes a task of its own, so no task holds an unbounded group.

Edge cases: null and empty texts have no words and fingerprint zero, and link like any
other; a text with fewer words than a shingle is one shingle; repeated rows and equal
doc_ids keep one row each; a null doc_id takes part but is never a component id unless the
component has no other.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

from repsum.llm.arrow import add_columns
from repsum.llm.columns import carry
from repsum.llm.components import connected_components
from repsum.plans.scratch import materialise

RADIUS = 3
BLOCKS = ((0, 13), (13, 13), (26, 13), (39, 13), (52, 12))  # (lowest bit, width), fixed
PIVOTS = 18
#: Different fingerprints of one key that one task compares; more are cut into pieces.
PIECE = 8192

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def fingerprint(text: str | None, words: int = 3, seed: int = 42) -> int:
    """Unsigned 64-bit SimHash of a text's lower-cased word shingles, repeats included."""
    tokens = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()  # bytes split at \x20 \x09-\x0d
    if not tokens:
        return 0
    joined = b" ".join(tokens)
    n = len(tokens)
    if n <= words:
        return xxhash.xxh64_intdigest(joined, seed)
    sizes = np.fromiter(map(len, tokens), np.int64, n) + 1
    ends = np.cumsum(sizes) - 1
    starts = ends - sizes + 1
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter((digest(joined[a:b], seed) for a, b in zip(starts[: n - words + 1].tolist(), ends[words - 1 :].tolist())), np.uint64, n - words + 1)
    return majority(hashes)


def majority(hashes: np.ndarray) -> int:
    """Bits that are set in over half of the hashes."""
    counts = np.zeros(64, np.int64)
    for begin in range(0, len(hashes), 1 << 14):
        some = hashes[begin : begin + (1 << 14)].astype("<u8").view(np.uint8).reshape(-1, 8)
        counts += np.unpackbits(some, axis=1, bitorder="little").sum(axis=0, dtype=np.uint32)
    return int.from_bytes(np.packbits(2 * counts > len(hashes), bitorder="little").tobytes(), "little")


def add_fingerprints(docs: DataFrame, text_col: str = "text", out: str = "fp", words: int = 3, seed: int = 42) -> DataFrame:
    """Append the fingerprint as a signed long with the same bits."""

    def work():
        def step(texts: list) -> dict:
            raw = np.fromiter((fingerprint(t, words, seed) for t in texts), np.uint64, len(texts))
            return {out: raw.view(np.int64)}

        return step

    return add_columns(docs, text_col, [T.StructField(out, T.LongType())], work)


def pivot_table(fps: np.ndarray, pivots: int = PIVOTS) -> np.ndarray:
    """Hamming distances of each fingerprint to the reference fingerprints."""
    steps = np.arange(1, pivots + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    steps = (steps ^ (steps >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    refs = steps ^ (steps >> np.uint64(31))
    return np.bitwise_count(fps[:, None] ^ refs[None, :]).astype(np.int8)


def near_pairs(fps: np.ndarray, table: np.ndarray, left: np.ndarray, right: np.ndarray, radius: int) -> np.ndarray:
    """Which index pairs are linked: pivot coordinates first, then the bits themselves."""
    alive = np.arange(len(left))
    for c in range(0, table.shape[1], 6):
        gap = np.abs(table[left[alive], c : c + 6] - table[right[alive], c : c + 6]).max(axis=1)
        alive = alive[gap <= radius]
    return alive[np.bitwise_count(fps[left[alive]] ^ fps[right[alive]]) <= radius]


def group_links(fps: np.ndarray, table: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest of the links within one group of different fingerprints."""
    order = np.argsort(table[:, 0], kind="stable")
    first = table[order, 0]
    parent = np.arange(len(fps))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    a: list[int] = []
    b: list[int] = []
    for begin in range(0, len(fps), 256):
        block = order[begin : begin + 256]
        stop = int(np.searchsorted(first, first[min(begin + 255, len(fps) - 1)] + radius, side="right"))
        for at in range(begin, stop, 2048):
            other = order[at : min(at + 2048, stop)]
            left, right = (x.ravel() for x in np.meshgrid(block, other, indexing="ij"))
            keep = np.flatnonzero(left != right)
            left, right = left[keep], right[keep]
            hit = near_pairs(fps, table, left, right, radius)
            for i, j in zip(left[hit].tolist(), right[hit].tolist()):
                x, y = root(i), root(j)
                if x != y:
                    parent[max(x, y)] = min(x, y)
                    a.append(i)
                    b.append(j)
    return fps[a], fps[b]


def sorted_links(keys: np.ndarray, fps: np.ndarray, tables: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within each run of equal keys; small runs all at once, lag by lag."""
    edge = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
    size = np.diff(np.append(edge, len(keys)))
    length = np.repeat(size, size)
    out_a, out_b = [], []
    small = np.flatnonzero((length > 1) & (length <= 32))
    if len(small):
        k, f, table = keys[small], fps[small], tables[small]
        for lag in range(1, int(length[small].max())):
            left = np.flatnonzero(k[:-lag] == k[lag:])
            hit = left[near_pairs(f, table, left, left + lag, radius)]
            out_a.append(f[hit])
            out_b.append(f[hit + lag])
    for begin, n in zip(edge[size > 32].tolist(), size[size > 32].tolist()):
        a, b = group_links(fps[begin : begin + n], tables[begin : begin + n], radius)
        out_a.append(a)
        out_b.append(b)
    return (np.concatenate(out_a), np.concatenate(out_b)) if out_a else (fps[:0], fps[:0])


def _block(low: int, width: int):
    return F.shiftrightunsigned(F.col("fp"), low).bitwiseAND(F.lit((1 << width) - 1))


def add_pivot_rows(distinct: DataFrame, pivots: int = PIVOTS) -> DataFrame:
    """(fp, row): each fingerprint with its distances to the reference fingerprints, a byte each."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            table = pivot_table(batch.column("fp").to_numpy().view(np.uint64), pivots)
            rows = pa.FixedSizeBinaryArray.from_buffers(pa.binary(pivots), len(table), [None, pa.py_buffer(np.ascontiguousarray(table))])
            yield pa.RecordBatch.from_arrays([batch.column("fp"), rows.cast(pa.binary())], names=["fp", "row"])

    return distinct.select("fp").mapInArrow(run, "fp long, row binary")


def deal(distinct: DataFrame) -> DataFrame:
    """(key, fp, row): each fingerprint under each choice of two bit blocks."""
    keys = [F.lit(n).cast("long") * F.lit(1 << 26) + _block(*BLOCKS[i]) * F.lit(1 << 13) + _block(*BLOCKS[j]) for n, (i, j) in enumerate(combinations(range(len(BLOCKS)), 2))]
    return distinct.select("fp", "row", F.explode(F.array(*keys)).alias("key"))


def fingerprint_links(distinct: DataFrame, radius: int = RADIUS, piece: int = PIECE) -> DataFrame:
    """(a, b): links of different fingerprints; every link joins what a path of these rows joins."""
    if radius > 3:
        raise ValueError("five blocks taken two at a time guarantee links up to 3 bits")
    dealt = deal(materialise(add_pivot_rows(distinct), "pivot-table"))
    large = materialise(dealt.groupBy("key").count().where(F.col("count") > piece), "large-keys")
    if not large.isEmpty():
        pieces = F.ceil(F.col("count") / piece).cast("int")
        own = F.pmod(F.xxhash64("fp"), pieces).cast("int")
        every = F.transform(F.sequence(F.lit(0), F.col("pieces") - 1), lambda o: F.struct(F.least(o, F.col("own")).alias("lo"), F.greatest(o, F.col("own")).alias("hi")))
        cut = dealt.join(large, "key").select("fp", "row", "key", pieces.alias("pieces"), own.alias("own")).select("fp", "row", "key", F.explode(every).alias("pair"))
        dealt = dealt.join(large, "key", "left_anti").select("fp", "row", "key", F.lit(0).alias("lo"), F.lit(0).alias("hi")).unionByName(cut.select("fp", "row", "key", F.col("pair.lo").alias("lo"), F.col("pair.hi").alias("hi")))
        dealt = dealt.select("fp", "row", F.xxhash64("key", "lo", "hi").alias("key"))  # keys that collide are compared in vain, no link is lost

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: tuple | None = None

        def emit(k: np.ndarray, f: np.ndarray, t: np.ndarray) -> pa.RecordBatch:
            a, b = sorted_links(k, f, t, radius)
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            table = np.frombuffer(b"".join(batch.column("row").to_pylist()), np.int8).reshape(batch.num_rows, -1)
            new = batch.column("key").to_numpy(), batch.column("fp").to_numpy().view(np.uint64), table
            k, f, t = new if rest is None else (np.concatenate(x) for x in zip(rest, new))
            cut = int(np.searchsorted(k, k[-1]))  # the last run may go on in the next batch
            if cut:
                yield emit(k[:cut], f[:cut], t[:cut])
            rest = k[cut:], f[cut:], t[cut:]
        if rest is not None:
            yield emit(*rest)

    return dealt.select("key", "fp", "row").repartition("key").sortWithinPartitions("key").mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, seed: int = 42, radius: int = RADIUS) -> DataFrame:
    """(doc_id, text_hash, fp, root, component_id) of every row.

    component_id is the smallest doc_id that links of at most ``radius`` bits reach; root is
    the component's smallest fingerprint and names it even where no doc_id is given.
    """
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("text_hash"), F.col(text_col).alias("text"))
    prints = materialise(add_fingerprints(src, "text", "fp", words, seed).select("doc_id", "text_hash", "fp"), "fingerprints")
    distinct = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    links = materialise(fingerprint_links(distinct.select("fp"), radius), "links")
    roots = connected_components(links)  # (node, root) of linked fingerprints only
    joined = distinct.join(roots, distinct["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    smallest = joined.groupBy("root").agg(F.min("least").alias("component_id"))
    named = joined.join(smallest, "root").select("fp", "root", "component_id")
    return prints.join(named, "fp").select("doc_id", "text_hash", "fp", "root", "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay: of each component the row of smallest doc_id (then text hash), once."""
    found = near_duplicates(docs)
    stay = found.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("n"), "doc_id", "text_hash")).alias("k"))
    stay = stay.select(F.col("k.doc_id").alias("_id"), F.col("k.text_hash").alias("_hash"))
    packed, unpack = carry(docs, ["doc_id", "text"])
    hashed = packed.withColumn("text_hash", F.xxhash64("text"))
    kept = hashed.join(stay, F.col("doc_id").cast("long").eqNullSafe(F.col("_id")) & (F.col("text_hash") == F.col("_hash")), "left_semi")
    return unpack(kept.dropDuplicates(["doc_id", "text_hash"]))
