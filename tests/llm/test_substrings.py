import collections
import hashlib
import random

import pytest

from repsum.llm import substrings
from repsum.llm.substrings import remove_repeats
from repsum.llm.suffixes import common_prefixes, suffix_array

from cases import odd_rows


def test_suffix_array_equals_sorting():
    rng = random.Random(5)
    for _ in range(800):
        s = [rng.randint(0, rng.choice([1, 2, 5, 40])) for _ in range(rng.randint(0, 60))]
        order = suffix_array(s)
        assert order == sorted(range(len(s)), key=lambda i: s[i:])
        same = common_prefixes(s, order)
        for r in range(1, len(s)):
            a, b = s[order[r - 1] :], s[order[r] :]
            n = 0
            while n < min(len(a), len(b)) and a[n] == b[n]:
                n += 1
            assert same[r] == n


def brute(rows, length):
    raws = [(d, (t or "").encode()) for d, t in rows]
    seen = collections.Counter(r[k : k + length] for _, r in raws for k in range(len(r) - length + 1))
    out = []
    for d, r in raws:
        mask = bytearray(len(r))
        for k in range(len(r) - length + 1):
            if seen[r[k : k + length]] > 1:
                mask[k : k + length] = b"\1" * length
        kept = bytes(b for b, m in zip(r, mask) if not m)
        spans = sum(1 for k in range(len(r)) if mask[k] and (k == 0 or not mask[k - 1]))
        out.append((d if d is not None else -1, len(r), sum(mask), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def run(df, **options):
    return sorted((r.doc_id if r.doc_id is not None else -1, r.n_bytes, r.n_removed, len(r.spans), r.kept_sha256) for r in remove_repeats(df, **options).collect())


def rows_with_repeats(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(rng.randint(1, 7)))
    passages = [" ".join(word() for _ in range(rng.randint(30, 90))) for _ in range(6)]
    rows = []
    for i in range(60):
        parts = [" ".join(word() for _ in range(rng.randint(0, 60)))]
        for _ in range(rng.randint(0, 3)):
            p = rng.choice(passages)
            a = rng.randint(0, len(p) // 2)
            parts += [p[a:], " ".join(word() for _ in range(rng.randint(0, 9)))]
        rows.append((i, " ".join(parts)))
    rows += [(100, "ab" * 500), (101, "z" * 900), (102, "z" * 205), (103, rows[3][1]), (103, rows[3][1])]
    near = rows[5][1]
    rows += [(200 + i, near[: 7 * i] + "#" + near[7 * i + 1 :]) for i in range(1, 25)]
    return rows


@pytest.mark.parametrize("crowd", [2048, 3])
def test_equals_brute_force(documents, crowd):
    rows = rows_with_repeats(crowd)
    assert run(documents(rows), crowd=crowd) == brute(rows, 200)


@pytest.mark.parametrize("depth", [0, 1, 6])
def test_a_common_passage_among_many_texts(documents, monkeypatch, depth):
    """A passage a little shorter and one a little longer than the strings, in texts that differ around it."""
    monkeypatch.setattr(substrings, "DEPTH", depth)
    rng = random.Random(depth)
    short, long = ("".join(rng.choice("abcdefgh ") for _ in range(n)) for n in (185, 215))
    rows = [(i, "".join(rng.choice("abcdefgh ") for _ in range(rng.randint(20, 90))) + (short if i % 3 else long) + "".join(rng.choice("ab") for _ in range(rng.randint(5, 60)))) for i in range(70)]
    assert run(documents(rows), crowd=8) == brute(rows, 200)


def test_odd_rows(odd):
    assert run(odd) == brute([r[:2] for r in odd_rows()], 200)


def test_empty(empty):
    assert run(empty) == []
