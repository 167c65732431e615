"""Benchmark decontamination with one Aho-Corasick automaton over normalised item windows.

Texts are normalised to lower-cased words joined by single spaces. Every window of ``n``
consecutive item words (an item of fewer words, but not none, is one window) becomes a
pattern, and one pass of the automaton over a document finds every occurrence, overlapping
ones too. Positions are mapped back to words, and for hit documents to character offsets of
the original text. Patterns are broadcast in blocks of bounded size and a worker process builds
a block's automaton once, whatever the tasks it runs. A benchmark beyond one block is scanned
block by block: passes over further blocks return only the rows that they hit, without their
texts, and the pass of the first block adds these to its own hits.

Edge cases: null texts have no words; items without words are in no window; repeated items
and items that share windows are all named; item ids are compared as strings, a null one as
the empty string; an empty benchmark hits nothing; other columns of the input are kept, and
those whose names this operator uses are overwritten.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections.abc import Iterator

import ahocorasick
import numpy as np
from pyspark import Broadcast
from pyspark.sql import DataFrame, functions as F, types as T

from repsum.llm.arrow import add_columns
from repsum.llm.columns import carry, quoted
from repsum.plans.scratch import materialise

WINDOW = 10
#: Pattern characters that one automaton holds at most (one item may exceed it alone).
BLOCK_CHARS = 8_000_000

#: Bytes of words: digits, letters (upper case lowered) and everything beyond ASCII.
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))
_ORIGINAL_WORD = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")

SPAN = T.ArrayType(T.StructType([T.StructField("begin", T.IntegerType()), T.StructField("end", T.IntegerType())]))
FIELDS = [
    T.StructField("n_words", T.LongType()),
    T.StructField("n_hit", T.LongType()),
    T.StructField("items", T.ArrayType(T.StringType())),
    T.StructField("word_runs", SPAN),
    T.StructField("char_spans", SPAN),
]


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_TABLE).split()


def windows_of(text: str | None, n: int = WINDOW) -> set[str]:
    """Patterns of one item: windows with a space at either end."""
    words = words_of(text)
    if not words:
        return set()
    runs = [words[i : i + n] for i in range(len(words) - n + 1)] or [words]
    return {f" {b' '.join(r).decode('utf-8', 'surrogatepass')} " for r in runs}


def pattern_blocks(benchmark: DataFrame, n: int = WINDOW, id_col: str = "item_id", text_col: str = "text") -> Iterator[dict[str, list[str]]]:
    """Windows with the items that hold them, in blocks of bounded size."""
    block: dict[str, list[str]] = {}
    held = 0
    rows = benchmark.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("i"), F.col(text_col).alias("t")).toLocalIterator()
    for row in rows:
        for w in windows_of(row["t"], n):
            if w not in block:
                held += len(w)
            block.setdefault(w, []).append(row["i"])
        if held >= BLOCK_CHARS:
            yield block
            block, held = {}, 0
    yield block


class Scanner:
    def __init__(self, patterns: dict[str, list[str]]) -> None:
        self.automaton = ahocorasick.Automaton()
        for w, items in patterns.items():
            self.automaton.add_word(w, (w.count(" ") - 1, tuple(items)))
        if patterns:
            self.automaton.make_automaton()
        self.empty = not patterns

    def scan(self, text: str | None) -> tuple[int, np.ndarray | None, set[str]]:
        """(words, mask of hit words or None, items with occurring windows)."""
        words = words_of(text)
        if self.empty or not words:
            return len(words), None, set()
        joined = f" {b' '.join(words).decode('utf-8', 'surrogatepass')} "
        found = list(self.automaton.iter(joined))
        if not found:
            return len(words), None, set()
        spaces = np.flatnonzero(np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32) == 32)
        last = np.searchsorted(spaces, np.array([e for e, _ in found]))
        step = np.zeros(len(words) + 1, np.int64)
        np.add.at(step, last - np.array([v[0] for _, v in found]), 1)
        np.add.at(step, last, -1)
        return len(words), np.cumsum(step[:-1]) > 0, set().union(*(v[1] for _, v in found))


def _runs(mask: np.ndarray) -> list[tuple[int, int]]:
    edge = np.flatnonzero(np.diff(np.concatenate([[0], mask.astype(np.int8), [0]])))
    return list(zip(edge[::2].tolist(), edge[1::2].tolist()))


def _spans(text: str, runs: list[tuple[int, int]]) -> list[dict]:
    at = [m.span() for m in _ORIGINAL_WORD.finditer(text)]
    return [{"begin": at[a][0], "end": at[b - 1][1]} for a, b in runs]


_SCANNERS: dict[str, Scanner] = {}


def _scanner(name: str, patterns: Broadcast) -> Scanner:
    """One automaton per worker process; it serves later tasks too, until another block comes."""
    if name not in _SCANNERS:
        _SCANNERS.clear()
        _SCANNERS[name] = Scanner(patterns.value)
    return _SCANNERS[name]


def _pass(docs: DataFrame, patterns: tuple[str, Broadcast], text_col: str, earlier_col: str | None = None) -> DataFrame:
    """One automaton over all rows; what other passes have found is in a column and is kept."""

    def work():
        scanner = _scanner(*patterns)

        def step(texts: list, earlier: list | None = None) -> dict:
            out: dict[str, list] = {f.name: [] for f in FIELDS}
            for k, text in enumerate(texts):
                n, mask, items = scanner.scan(text)
                for found in (earlier[k] or []) if earlier else []:
                    mask = np.zeros(n, bool) if mask is None else mask
                    for run in found["word_runs"]:
                        mask[run["begin"] : run["end"]] = True
                    items = items | set(found["items"])
                runs = [] if mask is None else _runs(mask)
                for name, value in (("n_words", n), ("n_hit", 0 if mask is None else int(mask.sum())), ("items", sorted(items)), ("word_runs", [{"begin": a, "end": b} for a, b in runs]), ("char_spans", _spans(text, runs) if runs else [])):
                    out[name].append(value)
            return out

        return step

    return add_columns(docs, text_col, FIELDS, work, also=earlier_col)


def scan_documents(docs: DataFrame, benchmark: DataFrame, n: int = WINDOW, text_col: str = "text") -> DataFrame:
    """Append n_words, n_hit, items, word_runs and char_spans (offsets in the original text) to every row."""
    context = docs.sparkSession.sparkContext

    def share(block: dict) -> tuple[str, Broadcast]:
        return uuid.uuid4().hex, context.broadcast(block)

    first, further = None, None
    for block in pattern_blocks(benchmark, n):
        if first is None:
            first = share(block)
        elif block:
            narrow = _pass(docs.select(F.col(text_col).alias("text")), share(block), "text").where("n_hit > 0")
            # rows of equal texts have equal hits: a text is known by two hashes of it
            hits = materialise(narrow.select(F.xxhash64("text").alias("h1"), F.md5("text").alias("h2"), F.struct("items", "word_runs").alias("hit")).distinct(), "block-hits")
            further = hits if further is None else further.unionByName(hits)
    if further is None:
        return _pass(docs, first, text_col)
    earlier = further.groupBy("h1", "h2").agg(F.collect_list("hit").alias("earlier_hits"))  # one entry per block at most
    packed, unpack = carry(docs, [text_col])
    own = [f.name for f in FIELDS]
    joined = packed.join(earlier, (F.xxhash64(text_col) == F.col("h1")) & (F.md5(text_col) == F.col("h2")), "left").drop("h1", "h2")
    scanned = _pass(joined, first, text_col, "earlier_hits")
    kept = [c for c in docs.columns if c.lower() not in {x.lower() for x in own}]
    return unpack(scanned, own).select(*map(quoted, kept), *(quoted(f"op_{x}").alias(x) for x in own))


def items_digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()


def digest(scanned: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    joined = F.array_join(F.array_sort("items"), ",")
    return scanned.select(F.col(id_col), "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(joined.cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))
