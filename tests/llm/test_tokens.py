import random
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from repsum.llm import token_planes as tp

from cases import odd_rows

PATH = public_tokenizers.path("byte_bpe_50k.json")


def expected(rows):
    tk = Tokenizer.from_file(PATH)
    out, start = [], 0
    for doc, text in rows:
        ids = np.array(tk.encode(text or "", add_special_tokens=False).ids + [0], "<u4")
        out.append((doc, len(ids), zlib.crc32(ids.tobytes())))
    return out


@pytest.mark.parametrize("layout", ["byte", "bit"])
def test_blocks_round_trip(layout):
    rng = np.random.default_rng(1)
    for n in (0, 1, 7, 8, 65, 1000):
        ids = rng.integers(0, 1 << 32, n, dtype=np.uint64).astype(np.uint32)
        sizes, ends, payload = tp.pack_blocks(ids, layout, 64, 1)
        assert sum(sizes) == n and len(ends) == len(sizes) * (4 if layout == "byte" else 32)
        assert (tp.unpack_blocks(sizes, ends, payload, layout) == ids).all()


def test_encoder_equals_the_library():
    tk = Tokenizer.from_file(PATH)
    e = tp.PieceEncoder(PATH, 0)
    rng = random.Random(3)
    parts = ["a", "B", "é", "ß", " ", "  ", "\n", "\t", "'s", "don't", "12", ".", ",!", "中", "🙂", "\x85", " ", "x_y", "<|endoftext|>", "²", "word", "-"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 14))) for _ in range(3000)]
    ids, sizes = e.encode(pa.array(texts))
    at = 0
    for text, n in zip(texts, sizes.tolist()):
        assert ids[at : at + n].tolist() == tk.encode(text, add_special_tokens=False).ids + [0], text
        at += n
    e.forget()
    again, _ = e.encode(pa.array(texts))
    assert (again == ids).all()


def test_added_tokens_as_the_library_encodes_them(spark, documents):
    name = "<|endoftext|>"
    texts = [name, f"x {name} y", f"{name}x", f"x{name}", f"a  {name}\n{name} b", f" {name} ", "<|endof text|>", "plain text", None, f"{name[:-1]} | {name}"]
    rows = [(i, t) for i, t in enumerate(texts)]
    got = tp.tokenise(documents(rows), PATH).orderBy("doc_id").collect()
    assert [(r.doc_id, r.n_tokens, r.ids_crc32) for r in got] == expected(rows)
    assert [r.start for r in got] == [sum(x.n_tokens for x in got[:i]) for i in range(len(got))]


def test_other_tokenizers_encode_whole_texts():
    wanted = [p for p in public_tokenizers.paths() if str(p).endswith(".json")] if hasattr(public_tokenizers, "paths") else [PATH]
    for path in wanted:
        tk, e = Tokenizer.from_file(str(path)), tp.PieceEncoder(str(path), 0)
        texts = ["Some plain words.", "two  spaces", " lead", "", "ünï <s> 12"]
        ids, sizes = e.encode(pa.array(texts))
        assert ids.tolist() == [i for t in texts for i in [*tk.encode(t, add_special_tokens=False).ids, 0]] and sizes.sum() == len(ids)


def test_odd_rows(spark, odd, tmp_path):
    got = tp.tokenise(odd, PATH, f"file://{tmp_path}/a").collect()
    assert sorted((r.doc_id or -1, r.n_tokens, r.ids_crc32) for r in got) == sorted((d or -1, n, c) for d, n, c in expected([r[:2] for r in odd_rows()]))
    ordered = sorted(got, key=lambda r: r.start)
    assert [r.start for r in ordered] == [sum(x.n_tokens for x in ordered[:i]) for i in range(len(ordered))]
    ids = [r.doc_id for r in ordered]
    assert ids[0] is None and ids[1:] == sorted(ids[1:])
    whole = tp.read_documents(tp.open_shelves(spark, f"file://{tmp_path}/a"), with_ids=True).collect()
    assert all(zlib.crc32(np.array(r.ids, "<u4").tobytes()) == r.ids_crc32 for r in whole)


def test_empty(empty):
    assert tp.tokenise(empty, PATH).count() == 0
