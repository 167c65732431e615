import random
import re

import numpy as np
import xxhash
from cases import odd_rows

from repsum.llm import pivots
from repsum.llm.components import connected_components


def brute_print(t):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(x).encode(), 42) for x in ([w[i : i + 3] for i in range(len(w) - 2)] or [w])]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(rows):
    fps = [brute_print(t) for _, t in rows]
    f = np.array(fps, np.uint64)
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in range(len(rows)):
        for b in np.flatnonzero(np.bitwise_count(f ^ f[a]) <= 3).tolist():
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    groups = {}
    for i in range(len(rows)):
        groups.setdefault(find(i), []).append(i)
    out = []
    for g in groups.values():
        known = [rows[i][0] for i in g if rows[i][0] is not None]
        least = min(known) if known else None
        out += [(str(rows[i][0]), fps[i], str(least)) for i in g]
    return sorted(out)


def run(df):
    return sorted((str(r.doc_id), r.fp & ((1 << 64) - 1), str(r.component_id)) for r in pivots.near_duplicates(df).collect())


def test_near_duplicates_equal_brute_force(documents):
    rng = random.Random(2)
    word = lambda: rng.choice(["alpha", "beta", "gamma", "delta", "eps", "zeta", "Eta", "théta"])
    rows = [(i, " ".join(word() for _ in range(rng.randint(0, 40)))) for i in range(150)]
    base = [word() for _ in range(220)]
    for i in range(80):
        copy = list(base)
        copy[rng.randrange(220)] = f"x{i}"
        rows.append((500 + i, " ".join(copy)))
    rows += [(400, rows[7][1]), (401, rows[7][1].upper()), (401, rows[7][1])]
    assert run(documents(rows)) == brute_components(rows)


def test_odd_and_empty(odd, empty):
    assert run(odd) == brute_components([r[:2] for r in odd_rows()])
    assert run(empty) == []


def test_links_of_planted_fingerprints(spark):
    rng = np.random.default_rng(4)
    base = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    fps = [int(x) for x in base]
    for x in base[:10]:
        for _ in range(30):
            bits = rng.choice(64, rng.integers(1, 5), replace=False)
            fps.append(int(x) ^ sum(1 << int(b) for b in bits))
    fps = sorted(set(fps))
    df = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in fps], "fp long")
    arr = np.array(fps, np.uint64)
    true = {(int(min(a, b)), int(max(a, b))) for i, a in enumerate(arr) for b in arr[i + 1 :][np.bitwise_count(arr[i + 1 :] ^ a) <= 3]}

    def parts(pairs):
        root = {x: x for x in fps}

        def find(i):
            while root[i] != i:
                i = root[i]
            return i

        for a, b in pairs:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
        return {x: find(x) for x in fps}

    for piece in (8192, 7):  # 7: keys are cut into pieces
        links = {(min(a, b), max(a, b)) for a, b in ((r.a & ((1 << 64) - 1), r.b & ((1 << 64) - 1)) for r in pivots.fingerprint_links(df, piece=piece).collect())}
        assert links <= true and parts(links) == parts(true)


def test_group_links_of_a_dense_group():
    rng = np.random.default_rng(9)
    x = rng.integers(0, 1 << 63, dtype=np.uint64)
    fps = np.unique(np.array([x ^ np.uint64(sum(1 << int(b) for b in rng.choice(14, 3, replace=False))) for _ in range(900)], np.uint64))
    a, b = pivots.group_links(fps, pivots.pivot_table(fps), 3)
    assert (np.bitwise_count(a ^ b) <= 3).all() and len(a) < len(fps)


def test_components(spark):
    rng = random.Random(1)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(1000 + i, 1001 + i) for i in range(60)] + [(5000, 5000 + i) for i in range(1, 90)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    root = {}

    def find(i):
        root.setdefault(i, i)
        while root[i] != i:
            i = root[i]
        return i

    for a, b in edges:
        if a != b:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    assert got == {i: find(i) for i in root}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_one_stays(documents):
    rows = [(3, "same words here now"), (2, "same words here now"), (2, "same words here now"), (5, None), (6, ""), (8, "quite a different text")]
    kept = pivots.keep_one(documents(rows))
    assert sorted(r.doc_id for r in kept.collect()) == [2, 5, 8] and "n_chars" in kept.columns
