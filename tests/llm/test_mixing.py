import re
from collections import defaultdict

import pytest
from cases import odd_rows

from repsum.llm.mixing import mix, repeat_documents


def targets(sizes):
    """Shares by weight with the excess of capped sources shared again until none is above."""
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None] * (None in sizes)
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(names)}
    total, out = 1.5 * sum(sizes.values()), {}
    open_ = list(names)
    while True:
        rest = total - sum(out.values())
        level = rest / max(1, sum(weight[s] for s in open_))
        over = [s for s in open_ if weight[s] * level > 2 * sizes[s] or sizes[s] == 0]
        if not over:
            return out | {s: weight[s] * level for s in open_}
        for s in over:
            out[s] = 2.0 * sizes[s]
            open_.remove(s)


def check(rows, got, slack):
    count = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    sizes = defaultdict(int)
    for r in rows:
        sizes[r[3]] += count(r[1])
    want = targets(dict(sizes))
    assert sorted((str(r[0]), count(r[1]), str(r[3])) for r in rows) == sorted((str(r.doc_id), r.size, str(r.source)) for r in got)
    taken = defaultdict(int)
    for r in got:
        assert 0 <= r.taken <= 2 * r.size and r.source_size == sizes[r.source] and r.target == pytest.approx(want[r.source])
        taken[r.source] += r.taken
    for s in want:
        assert abs(taken[s] - want[s]) <= slack


@pytest.mark.parametrize("block", [1, 16])
def test_targets_are_met(documents, block):
    rows = [(i, "w " * (i * 7919 % 60), "en", f"s{i % 5}" if i % 9 else None) for i in range(400)] + [(900, "v " * 3000, "en", "big"), (901, "tiny", "en", "zz")]
    df = documents(rows)
    got = mix(df, block=block).collect()
    check(rows, got, 4 * block)
    assert sorted(map(tuple, got), key=str) == sorted(map(tuple, mix(df.repartition(7), block=block).collect()), key=str)


def test_odd_and_empty(odd, empty):
    check([(*r, None, None)[:4] for r in odd_rows()], mix(odd, block=1).collect(), 4)
    assert mix(empty).count() == 0
    assert repeat_documents(empty).count() == 0


def test_repeats_follow_the_mix(documents):
    rows = [(i, f"doc {i} " + "w " * (5 + i % 9), "en", f"s{i % 3}") for i in range(200)]
    df = documents(rows)
    times = defaultdict(int)
    for r in repeat_documents(df, block=4).collect():
        times[r.doc_id] += 1
    for r in mix(df, block=4).collect():
        assert times[r.doc_id] == -(-r.taken // r.size)


def test_plan_is_native(documents):
    plan = mix(documents([(1, "a b", "en", "s")]))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan
