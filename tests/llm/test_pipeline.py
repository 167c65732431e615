import re

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline
from repsum.llm.pivots import fingerprint

SF = "/root/testdata/sf0.001"


def test_stages_keep_columns_and_decide(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = corpus_pipeline.materialise(stage(spark, docs, SF), f"test-{name}")
        seen[name] = before, docs
        if name != "tokens":
            assert docs.columns == before.columns
    before, after = seen["language"]
    lost = before.join(after, "doc_id", "left_anti").collect()
    assert len(lost) <= 0.02 * before.count()
    before, after = seen["near_duplicates"]
    kept = np.array([fingerprint(r.text) for r in after.collect()], np.uint64)
    assert all((np.bitwise_count(kept ^ f) <= 3).sum() == 1 for f in kept)
    every = [fingerprint(r.text) for r in before.collect()]
    assert all((np.bitwise_count(kept ^ np.uint64(f)) <= 3).any() for f in every) or len(kept) < len(every)
    before, after = seen["decontaminate"]
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", t.lower())
    items = [words(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    windows = {tuple(w[i : i + 10]) for w in items for i in range(len(w) - 9)}
    hit = {r.doc_id for r in before.collect() if any(tuple(words(r.text)[i : i + 10]) in windows for i in range(len(words(r.text)) - 9))}
    assert {r.doc_id for r in after.collect()} == {r.doc_id for r in before.collect()} - hit
    before, after = seen["mix"]
    assert {r.doc_id for r in after.collect()} <= {r.doc_id for r in before.collect()}
    assert seen["tokens"][1].count() == after.count()


def test_run_equals_stages(spark):
    got = corpus_pipeline.run(spark, SF)
    assert got.columns == ["doc_id", "start", "n_tokens", "ids_crc32"] and got.count() > 0


def test_stages_take_odd_and_empty_tables(spark, odd, empty, tmp_path):
    for docs in (odd, empty):
        for name, stage in corpus_pipeline.STAGES:
            docs = corpus_pipeline.materialise(stage(spark, docs, SF), f"odd-{name}")
            docs.count()


def test_language_stage_keeps_short_texts(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").cache()
    words = [r.text.split()[len(r.text.split()) // 2] for r in docs.orderBy("doc_id").collect() if r.text and r.text.strip()]
    rows = [(10_000_000 + i, w, None, "short", len(w)) for i, w in enumerate(words)] + [(20_000_000, "12 !", None, "short", 4)]
    both = docs.unionByName(spark.createDataFrame(rows, docs.select("doc_id", "text", "lang", "source", "n_chars").schema), allowMissingColumns=True)
    kept = {r.doc_id for r in corpus_pipeline.stage_language(spark, both, SF).select("doc_id").collect()}
    short = {i for i, w, *_ in rows if any(c.isalpha() for c in w)}
    print(f"short texts: {len(short)}, kept: {len(short & kept)}")
    assert short <= kept and 20_000_000 not in kept


def test_stages_keep_the_values_of_clashing_columns(spark):
    """Names that operators use inside, in any case, come out as they went in."""
    names = ["score", "N_WORDS", "n_hit", "_h", "_times", "Lang_Pred", "text_hash", "_id", "_source", "carried_row2", "a.b", "items", "h1", "fp", "root", "size"]
    given = spark.read.parquet(f"{SF}/documents.parquet")
    docs = given.select("*", *(F.concat(F.lit(f"{n}|"), F.col("doc_id").cast("string")).alias(n) for n in names))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = corpus_pipeline.materialise(stage(spark, docs, SF), f"clash-{name}")
        assert after.columns == docs.columns
        rows = [r.asDict() for r in after.collect()]
        assert rows and all(r[n] == f"{n}|{r['doc_id']}" for r in rows for n in names)
        before = {(r.doc_id, r.text, r.lang, r.source, r.n_chars) for r in given.collect()}
        assert all((r["doc_id"], r["text"], r["lang"], r["source"], r["n_chars"]) in before for r in rows)
        docs = after
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).count() == docs.count()
