import random
import re

import pytest

from repsum.llm import decontaminate as dc
from repsum.llm import licenses

from cases import odd_rows

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lowered(t):
    return WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))


def brute(rows, items):
    windows = {}
    for i, t in items:
        w = lowered(t)
        for x in [tuple(w[k : k + 10]) for k in range(len(w) - 9)] or ([tuple(w)] if w else []):
            windows.setdefault(x, set()).add(str(i) if i is not None else "")
    out = []
    for d, t in rows:
        w, hit, named = lowered(t), set(), set()
        for n in {len(x) for x in windows}:
            for k in range(len(w) - n + 1):
                if (x := tuple(w[k : k + n])) in windows:
                    hit |= set(range(k, k + n))
                    named |= windows[x]
        out.append((d if d is not None else -1, len(w), len(hit), len(named), dc.items_digest(list(named)), bool(hit)))
    return sorted(out)


ITEMS = [(1, "the quick brown FOX"), (2, "One two three four five six seven eight nine ten eleven twelve"), (3, None), (4, "... !"), (5, "three four five six seven eight nine ten eleven twelve"), (5, "brown fox"), (None, "lazy dog"), (10, "中文 🙂")]


@pytest.mark.parametrize("block", [8_000_000, 20])
def test_decontamination_equals_brute_force(spark, documents, monkeypatch, block):
    monkeypatch.setattr(dc, "BLOCK_CHARS", block)
    rows = [*odd_rows(), (20, "xx ONE two, three-four five six seven eight nine ten eleven twelve yy one two"), (21, "the the quick brown fox brown fox. lazy dog")]
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    scanned = dc.scan_documents(documents(rows), items)
    got = sorted((r.doc_id if r.doc_id is not None else -1, r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in dc.digest(scanned).collect())
    assert got == brute([r[:2] for r in rows], ITEMS)
    one = next(r for r in scanned.collect() if r.doc_id == 20)
    assert [one.text[s.begin : s.end] for s in one.char_spans] == ["ONE two, three-four five six seven eight nine ten eleven twelve"]


def test_empty_benchmark_and_documents(spark, odd, empty):
    none = spark.createDataFrame([], "item_id long, text string")
    assert dc.scan_documents(odd, none).where("n_hit > 0").count() == 0
    assert dc.digest(dc.scan_documents(empty, none)).count() == 0


def test_licenses(documents, odd, empty):
    rows = [
        (1, "Some text.\nReleased under the MIT License.\nMore text"),
        (2, "x\nLicensed under CC BY-NC 4.0.\n"),
        (3, "Licensed under CC BY 4.0."),
        (4, "we talk about a license to drive and the copyright of songs"),
        (5, "Licensed under the Apache License, Version 2.0.\n" * 2 + "\n\n" + "word " * 5000 + "\nThis work is licensed under the GNU General Public License, version 3."),
        (6, "This work is licensed under the GNU General Public License, version 2."),
        (7, licenses.TEMPLATES[3][1].replace("software and associated", "software and all associated")),
    ]
    got = {r.doc_id: r for r in licenses.scan_licenses(documents(rows)).collect()}
    names = {d: [m.license for m in r.matches] for d, r in got.items()}
    assert names == {1: ["MIT"], 2: ["CC-BY-NC-4.0"], 3: ["CC-BY-4.0"], 4: [], 5: ["Apache-2.0", "Apache-2.0", "GPL-3.0"], 6: ["GPL-2.0"], 7: ["MIT"]}
    m = got[1].matches[0]
    assert got[1].text[m.begin : m.end] == "Released under the MIT License" and m.saved > 0 and (m.missing, m.extra) == (0, 0)
    assert got[7].matches[0].extra == 1
    assert got[4].n_blocks > 0
    assert licenses.digest(licenses.scan_licenses(odd)).where("n_matches > 0").count() == 0
    assert licenses.digest(licenses.scan_licenses(empty)).count() == 0


@pytest.mark.parametrize("name, words", licenses.TEMPLATES)
def test_license_in_a_large_block_is_found(name, words):
    """Cues without a blank line between them make one block, in which a short statement saves nothing."""
    rng = random.Random(5)
    known = ["".join(rng.choice("abcdefghijklmnopqrst") for _ in range(rng.randint(2, 9))) for _ in range(400)]
    prose = [" ".join(rng.choices(known, k=140)) for _ in range(80)]
    text = "\nlicense ".join([*prose[:40], words, *prose[40:]])
    got = licenses.Templates().scan(text)
    assert got["n_blocks"] == 1 and [m["license"] for m in got["matches"]] == [name]
    m = got["matches"][0]
    assert text[m["begin"] : m["end"]] == words.rstrip("./)") and (m["missing"], m["extra"]) == (0, 0)


def test_every_occurrence_of_a_license_counts(documents):
    apache, gpl = licenses.TEMPLATES[4][1], licenses.TEMPLATES[12][1]
    near = licenses.TEMPLATES[3][1].replace("software and associated", "software and all associated")
    rows = [(1, f"{apache}\n" * 2), (2, f"{apache} {gpl} " * 3), (3, f"{near}\n{near}\n{licenses.TEMPLATES[3][1]}")]
    scanned = licenses.scan_licenses(documents(rows))
    got = {r.doc_id: r for r in scanned.collect()}
    assert {d: [m.license for m in r.matches] for d, r in got.items()} == {1: ["Apache-2.0"] * 2, 2: ["Apache-2.0", "GPL-2.0"] * 3, 3: ["MIT"] * 3}
    assert [m.extra for m in got[3].matches] == [1, 1, 0]
    for r in got.values():
        assert all(a.end <= b.begin for a, b in zip(r.matches, r.matches[1:]))
    assert {r.doc_id: r.n_matches for r in licenses.digest(scanned).collect()} == {1: 2, 2: 6, 3: 3}


def holds(want, words, allowed):
    """(differences, begin, end) of the closest in-order alignment that starts at words[0], or None."""
    best = None
    for skipped in range(min(allowed, len(want) - 1) + 1):  # template words missing before the first match
        if words[0] != want[skipped]:
            continue
        # cost[j]: least differences once j template words are dealt with and the last word matched
        reach = {skipped + 1: (skipped, 1)}
        frontier = [(skipped, skipped + 1, 1)]
        while frontier:
            cost, j, at = frontier.pop()
            end = (cost + len(want) - j, at)
            if end[0] <= allowed and (best is None or end < best):
                best = end
            for more in range(allowed - cost + 1):
                for gone in range(allowed - cost - more + 1):
                    if at + more < len(words) and j + gone < len(want) and words[at + more] == want[j + gone]:
                        frontier.append((cost + more + gone, j + gone + 1, at + more + 1))
    return best


def test_licenses_equal_a_brute_force_scan():
    """Every place that a word-by-word search of all templates accepts is found, and no other."""
    rng = random.Random(9)
    word = re.compile(r"[^\W_]+")
    texts = []
    for _ in range(60):
        parts = []
        for _ in range(rng.randint(1, 4)):
            name, wording = rng.choice(licenses.TEMPLATES)
            w = wording.split()
            for _ in range(rng.choice([0, 0, 1, 2, 4])):
                at = rng.randrange(len(w))
                w[at : at + rng.choice([0, 1])] = rng.choice([[], ["extra"], ["other", "words"]])
            parts += [" ".join(rng.choices(["license", "holds", "for", "prose", "copyright"], k=rng.randint(1, 9))), " ".join(w)]
        texts.append("\n".join(parts))
    own = licenses.Templates()
    for text in texts:
        got = own.scan(text)["matches"]
        at = [m.span() for m in word.finditer(text)]
        words = [text[a:b].lower() for a, b in at]
        places = []
        for want, allowed in zip(own.words, own.allowed):
            for x in range(len(words)):
                found = holds(want, words[x : x + len(want) + allowed], allowed)
                if found:
                    places.append((found[0], at[x][0], at[x + found[1] - 1][1]))
        for differences, a, b in places:  # a place is found, or words of it belong to a match that is as close
            assert any(m["begin"] < b and a < m["end"] for m in got), text[a:b]
        for m in got:
            assert any(m["missing"] + m["extra"] >= d and a >= m["begin"] and b <= m["end"] for d, a, b in places), m
        least = min((d for d, *_ in places), default=None)
        assert least is None or min(m["missing"] + m["extra"] for m in got) == least


@pytest.mark.parametrize("text, name", [("Redistribution and use in source and binary forms, with or without\nmodification, are permitted provided that the following conditions are met:", "BSD"), ("Apache License\n   Version 2.0, January 2004\n   http://www.apache.org/licenses/", "Apache-2.0"), ("The MIT License (MIT)", "MIT"), ("available under the MIT license", "MIT")])
def test_heads_of_full_license_texts(text, name):
    assert [m["license"] for m in licenses.Templates().scan(text)["matches"]] == [name]


def test_blocks_of_patterns_keep_clashing_columns(spark, monkeypatch):
    monkeypatch.setattr(dc, "BLOCK_CHARS", 20)
    docs = spark.createDataFrame([(1, "xx the QUICK brown fox. lazy dog", 7, "h"), (1, "xx the QUICK brown fox. lazy dog", 7, "h"), (2, None, 8, None)], "doc_id long, text string, N_Words long, h1 string")
    got = dc.scan_documents(docs, spark.createDataFrame(ITEMS, "item_id long, text string")).collect()
    assert got[0].__fields__ == ["doc_id", "text", "h1", "n_words", "n_hit", "items", "word_runs", "char_spans"]
    assert sorted((r.doc_id, r.n_words, r.n_hit, r.items, r.h1) for r in got) == [(1, 7, 6, ["", "1", "5"], "h")] * 2 + [(2, 0, 0, [], None)]
