"""Token ids as bit- or byte-plane blocks.

Texts are encoded with a public tokenizer, an end id closes each document, and the ids are
cut into fixed-size blocks. A block is transposed into planes (all first bytes, all second
bytes, ... or all lowest bits, ...), so that the slowly varying high planes become long runs,
and each plane is compressed with zstandard on its own. One stored row, a *shelf*, holds the
blocks of a run of whole documents with its chunk index: for each block its id count and the
end of each of its planes in the payload; for each document its id and its number of ids.
Shelves are Parquet rows, so that any Hadoop file system can hold them and a lost executor's
output is never half visible.

Edge cases: a null text counts as empty and yields the end id alone; an empty table yields
no shelf; rows that share a doc_id are kept, in order of their text's hash; a null doc_id
sorts first; a text of any length lies in one shelf, cut into as many blocks as it needs; an
added token of the tokenizer inside a text is encoded as the library encodes it, as that token;
other columns of the input are ignored.
"""

from __future__ import annotations

import gc
import os
import re
import zlib
from collections.abc import Callable, Iterable, Iterator
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window, functions as F, types as T

from repsum.llm.arrow import slices
from repsum.plans.scratch import new_path

#: Ids in a block, and ids after which a shelf is closed at the next document.
BLOCK_IDS = 1 << 16
SHELF_IDS = 1 << 18
#: Text bytes encoded at once.
ENCODE_BYTES = 4 << 20
#: Distinct pieces and pre-tokens whose ids a worker remembers.
CACHE_PIECES = 800_000

#: A single space between two characters that are not white space: every such space opens a
#: new pre-token of the byte-level pattern, so ids on both sides do not depend on each other.
_SAFE_SPACE = re.compile(r"(?<=\S) (?=\S)")
_MARKS = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum())

SHELF = T.StructType(
    [
        T.StructField("part", T.IntegerType(), False),
        T.StructField("shelf", T.LongType(), False),
        T.StructField("start_in_part", T.LongType(), False),
        T.StructField("n_ids", T.LongType(), False),
        T.StructField("layout", T.StringType(), False),
        T.StructField("doc_ids", T.ArrayType(T.LongType()), False),
        T.StructField("doc_lens", T.ArrayType(T.LongType()), False),
        T.StructField("block_ids", T.ArrayType(T.IntegerType()), False),
        T.StructField("plane_ends", T.ArrayType(T.LongType()), False),
        T.StructField("payload", T.BinaryType(), False),
    ]
)


class PieceEncoder:
    """Whole-text encoding, equal to the library's, that asks its model once per distinct pre-token.

    Texts are cut at single spaces, the distinct pieces of a batch are looked up, and unknown
    ones are pre-tokenised and merged by the tokenizer; ids of a batch are then gathered at once.
    """

    def __init__(self, path: str, end_id: int, remember: int = CACHE_PIECES) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel

        self.tokenizer = Tokenizer.from_file(path)
        self.added = sorted({t.content for t in self.tokenizer.get_added_tokens_decoder().values()})
        self.end_id = end_id
        self.remember = remember
        before = self.tokenizer.pre_tokenizer
        self.fast = isinstance(before, ByteLevel) and before.use_regex and not before.add_prefix_space and self.tokenizer.normalizer is None
        self.tokenize = self.tokenizer.model.tokenize
        self.pre_tokenize = self.tokenizer.pre_tokenizer.pre_tokenize_str if self.fast else None
        if self.fast:  # the printable stand-in of each byte, as the pre-tokenizer writes it
            whole = ByteLevel(add_prefix_space=False, use_regex=False)
            self.stand_in = {}
            for sample in map(chr, [*range(1, 0x250), *range(0x800, 0xD800, 0x40), *range(0x10000, 0x110000, 0x1000)]):
                self.stand_in |= zip(sample.encode(), whole.pre_tokenize_str(sample)[0][0])
            self.space = self.stand_in[32]
        self.clear()

    def clear(self) -> None:
        self.inner: dict[str, int] = {}
        self.first: dict[str, int] = {}
        self.token: dict[str, tuple[int, ...]] = {}
        self.pool = np.empty(1 << 16, np.uint32)
        self.ends = np.zeros(1 << 14, np.int64)  # ends[i] closes piece i - 1; ends[0] is 0
        self.count = 0
        self.uses = np.zeros(1 << 14, np.uint8)
        self._store([(self.end_id,)])  # piece 0 closes a document

    def forget(self) -> None:
        """Keep the pieces that most batches have used, a third of what may be remembered at most."""
        names = list(self.inner)
        at = np.fromiter(self.inner.values(), np.int64, len(names))
        used = self.uses[at]
        least = 2
        while np.count_nonzero(used >= least) > self.remember // 3 and least < 255:
            least += 1
        keep = [(names[i], at[i]) for i in np.flatnonzero(used >= least).tolist()]
        pool, ends = self.pool, self.ends
        self.clear()
        if len(keep) <= self.remember // 3:
            self.inner = {p: n for n, (p, _) in enumerate(keep, self.count)}
            self._store([pool[ends[i] : ends[i + 1]].tolist() for _, i in keep])
            self.uses[1 : self.count] = 1

    def _store(self, pieces: list) -> None:
        sizes = np.fromiter(map(len, pieces), np.int64, len(pieces))
        ids = np.fromiter(chain.from_iterable(pieces), np.uint32, int(sizes.sum()))
        held, n = int(self.ends[self.count]), len(pieces)
        while held + len(ids) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.empty_like(self.pool)])
        while self.count + n + 1 > len(self.ends):
            self.ends = np.concatenate([self.ends, np.zeros_like(self.ends)])
            self.uses = np.concatenate([self.uses, np.zeros_like(self.uses)])
        self.pool[held : held + len(ids)] = ids
        self.ends[self.count + 1 : self.count + n + 1] = held + np.cumsum(sizes)
        self.count += n

    def _merge(self, token: str) -> tuple[int, ...]:
        known = self.token.get(token)
        if known is None:
            known = self.token[token] = tuple([t.id for t in self.tokenize(token)])
        return known

    def _whole(self, text: str) -> list[int]:
        return [i for token, _ in self.pre_tokenize(text) for i in self._merge(token)] if text else []

    def _inner_pieces(self, pieces: list[str]) -> list:
        """Ids of pieces that follow a space."""
        out, token, tokenize, space, stand_in = [], self.token, self.tokenize, self.space, self.stand_in
        for p in pieces:
            core = p if p.isalpha() else p.rstrip(_MARKS)
            if core.isalpha():  # one pre-token of letters, then at most one of ASCII marks
                name = space + core if core.isascii() else space + core.encode().decode("latin-1").translate(stand_in)
                ids = token.get(name)
                if ids is None:
                    ids = token[name] = tuple([t.id for t in tokenize(name)])
                out.append(ids if len(core) == len(p) else ids + self._merge(p[len(core) :]))
            else:
                out.append(self._lines(p) or self._whole(" " + p))
        return out

    def _lines(self, piece: str) -> tuple[int, ...] | None:
        """Ids of lines of letters and marks within a piece; a line feed between them is a pre-token of its own."""
        lines, out, lead = piece.split("\n"), (), self.space
        for line in lines:
            core = line.rstrip(_MARKS)
            if not core.isalpha():
                return None
            name = core if core.isascii() else core.encode().decode("latin-1").translate(self.stand_in)
            if out:
                out += self._merge(self.stand_in[10])
            out += self._merge(lead + name)
            if len(core) < len(line):
                out += self._merge(line[len(core) :])
            lead = ""
        return out

    def _numbers(self, pieces: list[str], into: dict[str, int], learn: Callable[[list[str]], list]) -> np.ndarray:
        """Numbers of a batch's different pieces."""
        numbers = np.fromiter(map(into.get, pieces, repeat(-1)), np.int64, len(pieces))
        missing = np.flatnonzero(numbers < 0)
        if len(missing):
            news = [pieces[i] for i in missing.tolist()]
            numbers[missing] = np.arange(self.count, self.count + len(news))
            into.update(zip(news, range(self.count, self.count + len(news))))
            self._store(learn(news))
        self.uses[numbers] = np.minimum(self.uses[numbers], 254) + 1
        return numbers

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, the end id after each; number of ids of each text).

        The library looks for added tokens before it does anything else, so a text that holds the
        wording of one goes to the library whole; so do all texts if its steps are not byte-level.
        """
        whole = np.full(len(texts), not self.fast)
        for content in self.added:
            whole |= pc.match_substring(texts, content).to_numpy(zero_copy_only=False)
        if not whole.any():
            return self._pieced(texts)
        ids, sizes = self._pieced(pc.if_else(pa.array(whole), "", texts))
        ends, parts, at = np.cumsum(sizes), [], 0
        for i in np.flatnonzero(whole).tolist():  # a lone end id stands where each of these texts belongs
            made = self.tokenizer.encode(texts[i].as_py(), add_special_tokens=False).ids
            parts += [ids[at : ends[i] - 1], np.array(made, np.uint32)]
            at = int(ends[i]) - 1
            sizes[i] = len(made) + 1
        return np.concatenate([*parts, ids[at:]]), sizes

    def _pieced(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The same for texts that may be cut at single spaces."""
        if len(self.inner) + len(self.first) + len(self.token) > self.remember:
            self.forget()
        lists = pc.split_pattern(texts, " ")
        coded = lists.flatten().dictionary_encode()
        names = coded.dictionary.to_pylist()
        unsafe = [i for i, n in enumerate(names) if not n or n[0].isspace() or n[-1].isspace()]
        if unsafe:  # some other space stands beside white space: those texts are cut with care
            flat = np.isin(coded.indices.to_numpy(), unsafe)
            ends = lists.offsets.to_numpy().astype(np.int64) - lists.offsets[0].as_py()
            odd = np.diff(np.append(0, np.cumsum(flat))[ends]) > 0
            lists = pa.array([_SAFE_SPACE.split(t) if o else t.split(" ") for t, o in zip(texts.to_pylist(), odd)], pa.list_(pa.string()))
            coded = lists.flatten().dictionary_encode()
            names = coded.dictionary.to_pylist()
        starts = lists.offsets.to_numpy().astype(np.int64) - lists.offsets[0].as_py()
        number = self._numbers(names, self.inner, self._inner_pieces)
        index = coded.indices.to_numpy()
        at = number[index]
        heads = starts[:-1]
        which, back = np.unique(index[heads], return_inverse=True)
        at[heads] = self._numbers([names[i] for i in which], self.first, lambda new: list(map(self._whole, new)))[back]
        at = np.insert(at, starts[1:], 0)
        ends = starts[1:] + np.arange(1, len(starts))
        begin = self.ends[at]
        size = self.ends[at + 1] - begin
        upto = np.cumsum(size)
        ids = self.pool[np.repeat(begin - (upto - size), size) + np.arange(int(upto[-1]) if len(upto) else 0)]
        return ids, np.diff(upto[ends - 1], prepend=0)


def to_planes(ids: np.ndarray, layout: str) -> list[bytes]:
    """The planes of one block, lowest first. A block's last bit plane is padded to whole bytes."""
    if layout == "byte":
        return [row.tobytes() for row in ids.astype("<u4").view(np.uint8).reshape(-1, 4).T]
    bits = np.unpackbits(ids.astype("<u4").view(np.uint8).reshape(-1, 4), axis=1, bitorder="little")
    return [np.packbits(row).tobytes() for row in bits.T]


def from_planes(planes: list[bytes], n: int, layout: str) -> np.ndarray:
    if layout == "byte":
        return np.ascontiguousarray(np.stack([np.frombuffer(p, np.uint8) for p in planes], 1)).view("<u4").ravel()
    bits = np.stack([np.unpackbits(np.frombuffer(p, np.uint8))[:n] for p in planes], 1)
    return np.packbits(bits, axis=1, bitorder="little").view("<u4").ravel()


def pack_blocks(ids: np.ndarray, layout: str, block: int, level: int) -> tuple[list[int], list[int], bytes]:
    """(ids of each block, end of each plane in the payload, payload)."""
    squeeze, sizes, ends, body, at = zstandard.ZstdCompressor(level=level), [], [], [], 0
    for begin in range(0, len(ids), block):
        some = ids[begin : begin + block]
        sizes.append(len(some))
        for plane in to_planes(some, layout):
            body.append(squeeze.compress(plane))
            at += len(body[-1])
            ends.append(at)
    return sizes, ends, b"".join(body)


def unpack_blocks(sizes: list[int], ends: list[int], payload: bytes, layout: str) -> np.ndarray:
    expand, per, begin, out = zstandard.ZstdDecompressor(), 4 if layout == "byte" else 32, 0, []
    for i, n in enumerate(sizes):
        planes = []
        for end in ends[i * per : (i + 1) * per]:
            planes.append(expand.decompress(payload[begin:end]))
            begin = end
        out.append(from_planes(planes, n, layout))
    return np.concatenate(out) if out else np.empty(0, np.uint32)


def write_shelves(docs: DataFrame, path: str, tokenizer: str, end_id: int = 0, layout: str = "byte", block: int = BLOCK_IDS, shelf: int = SHELF_IDS, level: int = 1, remember: int = CACHE_PIECES, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encode whole texts in ascending doc_id order and write them in the plane format below ``path``.

    Texts are dealt by range before they are encoded: the one shuffle moves texts, and what the
    range bounds are sampled from costs no encoding.
    """
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).withColumn("tie", F.xxhash64("text"))
    ordered = src.repartitionByRange("doc_id", "tie").sortWithinPartitions("doc_id", "tie").select("doc_id", "text")
    types = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.binary()]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(tokenizer, end_id, remember)
        part, number, start, total = TaskContext.get().partitionId(), 0, 0, 0
        ids: list[np.ndarray] = []
        docs: list[list] = []
        lens: list[np.ndarray] = []

        def close() -> pa.RecordBatch:
            nonlocal number, start, total
            sizes, ends, payload = pack_blocks(np.concatenate(ids), layout, block, level)
            row = [part, number, start, total, layout, [d for x in docs for d in x], np.concatenate(lens).tolist(), sizes, ends, payload]
            number, start, total = number + 1, start + total, 0
            for held in (ids, docs, lens):
                held.clear()
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, types)], names=SHELF.fieldNames())

        for whole in batches:
            for some in slices(whole, "text", ENCODE_BYTES):
                made, sizes = encoder.encode(some.column("text"))
                ids.append(made)
                docs.append(some.column("doc_id").to_pylist())
                lens.append(sizes)
                total += len(made)
                if total >= shelf:
                    yield close()
        if docs:
            yield close()

    ordered.mapInArrow(run, SHELF).write.option("compression", "uncompressed").parquet(path)


_ENCODERS: dict[tuple[str, int, int], PieceEncoder] = {}


def _encoder(path: str, end_id: int, remember: int) -> PieceEncoder:
    """One encoder per worker process; its memory of pieces serves later tasks too."""
    if (path, end_id, remember) not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[path, end_id, remember] = PieceEncoder(path, end_id, remember)
    return _ENCODERS[path, end_id, remember]


def open_shelves(spark, path: str) -> DataFrame:
    return spark.read.schema(SHELF).parquet(path)


def read_documents(shelves: DataFrame, with_ids: bool = False) -> DataFrame:
    """(part, start_in_part, doc_id, n_tokens, ids_crc32[, ids]) of each stored document."""
    schema = "part int, start_in_part long, doc_id long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if _ENCODERS:  # a worker that has encoded serves other stages from here on
            _ENCODERS.clear()
            gc.collect()
            pa.default_memory_pool().release_unused()
        for batch in batches:
            for i in range(batch.num_rows):
                row = {n: batch.column(n)[i].as_py() for n in batch.schema.names}
                ids = unpack_blocks(row["block_ids"], row["plane_ends"], row["payload"], row["layout"])
                lens = np.array(row["doc_lens"], np.int64)
                ends = np.cumsum(lens)
                raw = memoryview(ids.astype("<u4").tobytes())
                crcs = [zlib.crc32(raw[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), lens.tolist())]
                columns = [pa.array([row["part"]] * len(lens), pa.int32()), pa.array(row["start_in_part"] + ends - lens, pa.int64()), pa.array(row["doc_ids"], pa.int64()), pa.array(lens), pa.array(crcs, pa.int64())]
                names = ["part", "start_in_part", "doc_id", "n_tokens", "ids_crc32"]
                if with_ids:
                    columns.append(pa.array([ids[e - n : e].tolist() for e, n in zip(ends.tolist(), lens.tolist())], pa.list_(pa.int64())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return shelves.mapInArrow(run, schema)


def part_offsets(shelves: DataFrame) -> DataFrame:
    """(part, offset): ids stored before each part. One row per written partition."""
    totals = shelves.groupBy("part").agg(F.sum("n_ids").alias("n"))
    return totals.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))


def tokenise(docs: DataFrame, tokenizer: str, path: str | None = None, end_id: int = 0, layout: str = "byte", remember: int = CACHE_PIECES) -> DataFrame:
    """Encode, write, read back: (doc_id, start, n_tokens, ids_crc32) of each document.

    ``remember`` pieces are held by each worker, some 250 bytes each; fewer cost time, not results.
    """
    spark = docs.sparkSession
    path = path or new_path(spark, "token-planes")
    write_shelves(docs, path, tokenizer, end_id, layout, remember=remember)
    shelves = open_shelves(spark, path)
    offsets = part_offsets(shelves)  # bounded by the number of written partitions, whatever the rows
    return read_documents(shelves).join(F.broadcast(offsets), "part").select("doc_id", (F.col("offset") + F.col("start_in_part")).alias("start"), "n_tokens", "ids_crc32")
