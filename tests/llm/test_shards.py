import random
import zlib
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from repsum.llm import kdshards
from repsum.llm.kdshards import place_large, shard_documents

from cases import odd_rows


def check(rows, got, shards):
    assert sorted(((r.doc_id if r.doc_id is not None else -1), r.size, r.text_crc32) for r in got) == sorted(((d if d is not None else -1), len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for d, t in rows)
    slots = defaultdict(list)
    for r in got:
        assert 0 <= r.shard < shards
        slots[r.shard].append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())


@pytest.mark.parametrize("law", ["bytes", "rows"])
def test_balance_and_groups(documents, law):
    rows = [(i, f"text {i} " + "lorem ipsum " * (i * 37 % 90), "en", f"s{i % 7}") for i in range(3000)] + [(5000 + i, "a copy that many share " * 9, "en", f"s{i % 7}") for i in range(40)]
    got = shard_documents(documents(rows), 16, law).collect()
    check([r[:2] for r in rows], got, 16)
    load = defaultdict(int)
    for r in got:
        load[r.shard] += r.size if law == "bytes" else 1
    assert max(load.values()) <= 1.03 * sum(load.values()) / 16
    assert len({r.shard for r in got if r.doc_id >= 5000}) == 1


def test_oversized_group_is_spread(documents):
    rows = [(i, f"own text {i} " * 3, "en", "s") for i in range(400)] + [(1000 + i, "the very same text " * 20, "en", "s") for i in range(600)]
    got = shard_documents(documents(rows), 8).collect()
    check([r[:2] for r in rows], got, 8)
    load = defaultdict(int)
    for r in got:
        load[r.shard] += r.size
    assert max(load.values()) <= 1.02 * sum(load.values()) / 8


def test_place_large_fills_the_most_room_first():
    room = [10.0, 10.0]
    whole, spread = place_large([(("a",), 15.0), (("b",), 4.0)], room)
    assert whole == {("b",): 1} and sum(p for p, _ in spread[("a",)]) == pytest.approx(1) and sum(room) == pytest.approx(1)


def test_odd_and_empty(odd, empty):
    check([r[:2] for r in odd_rows()], shard_documents(odd).collect(), 16)
    assert shard_documents(empty).count() == 0


def test_unknown_law(odd):
    with pytest.raises(ValueError):
        shard_documents(odd, 4, "key")


def naive_tree(groups, room):
    """Shard of each group by a plain recursion over sorted lists; groups: (hash, weight, {dimension: coordinate}, tie)."""
    out = {}

    def split(some, a, b):
        if b - a == 1:
            out.update({g[0]: a for g in some})
            return
        middle = (a + b) // 2
        left, right = (sum(max(0.0, x) for x in room[i:j]) for i, j in ((a, middle), (middle, b)))
        if not some:
            return
        wide = max(kdshards.DIMENSIONS, key=lambda d: max(g[2][d] for g in some) - min(g[2][d] for g in some))
        goal = sum(g[1] for g in some) * (left / (left + right) if left + right > 0 else 0.5)
        order = sorted(some, key=lambda g: (g[2][wide], g[3]))
        below, cut = 0.0, len(order)
        for n, g in enumerate(order):
            if below + g[1] >= goal:
                cut = n + (goal - below > g[1] / 2)
                break
            below += g[1]
        split(order[:cut], a, middle)
        split(order[cut:], middle, b)

    split(groups, 0, len(room))
    return out


@pytest.mark.parametrize("law", ["bytes", "rows"])
def test_shards_equal_a_plain_recursion(documents, monkeypatch, law):
    """With quantiles refined to the last key, the distributed tree is that of sorted lists."""
    monkeypatch.setattr(kdshards, "FINE", 0.0)
    rng = random.Random(3)
    rows = [(i, f"text {i} " + "lorem ipsum " * rng.randint(0, 60), rng.choice(["en", "de", None]), f"s{rng.randint(0, 8)}") for i in range(260)] + [(1000 + i, "a copy that many share " * 40, "en", "s1") for i in range(12)]
    docs = documents(rows)
    groups = kdshards.groups_of(kdshards.sized_rows(docs), law).collect()
    total = sum(g.weight for g in groups)
    monkeypatch.setattr(kdshards, "LARGE", 0.3)
    room = [total / 8] * 8
    limit = 0.3 * total / 8
    large = sorted((((g.text_hash, g.size, g.text_crc32), float(g.weight)) for g in groups if g.weight > limit), key=lambda x: (-x[1], x[0]))
    whole, spread = place_large(large, room)
    assert whole and not spread
    want = {k[0]: shard for k, shard in whole.items()}
    want |= naive_tree([(g.text_hash, g.weight, {"length": g.length, "origin": g.origin, "tongue": g.tongue}, g.tie) for g in groups if g.weight <= limit], room)
    hashes = {(r.doc_id): r.text_hash for r in docs.select("doc_id", F.xxhash64("text").alias("text_hash")).collect()}
    got = shard_documents(docs, 8, law).collect()
    assert all(r.shard == want[hashes[r.doc_id]] for r in got) and len(got) == len(rows)
