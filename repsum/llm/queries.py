"""Driver queries of the operators in this package: thin digests of what each operator returns."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, functions as F

from repsum.llm import additive, decontaminate, importance, kdshards, language, licenses, mixing, pivots, substrings, token_planes
from repsum.plans.scratch import ship_package

#: The tokenizer file of the production queries; operators take any path.
TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return licenses.digest(licenses.scan_licenses(docs))


def op2_token_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_planes.tokenise(_table(spark, sf_dir, "documents"), TOKENIZER)


def op3_repeated_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = substrings.remove_repeats(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), "kept_sha256")


def op4_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = kdshards.shard_documents(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return decontaminate.digest(decontaminate.scan_documents(docs, _table(spark, sf_dir, "benchmark")))


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = language.fit(docs.where(~language.held_out()))
    return language.predict(docs.select("doc_id", "text"), model).select("doc_id", language.held_out().alias("held_out"), "lang_pred", "score")


def op7_additive_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return additive.search(_table(spark, sf_dir, "embeddings"), lambda vec_id: vec_id % 20 == 0)


def op8_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op9_simhash_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pivots.near_duplicates(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op10_importance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Target: rows labelled good and not toxic; as many rows are drawn as the labels say are good."""
    labels = _table(spark, sf_dir, "labels")
    good = (F.col("quality") == 1) & (F.col("toxic") == 0)
    share = labels.agg(F.avg(good.cast("double"))).head()[0]
    return importance.resample(_table(spark, sf_dir, "documents"), labels.where(good), share if share is not None else 1.0)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_license_scan": op1_license_scan,
    "op2_token_planes": op2_token_planes,
    "op3_repeated_strings": op3_repeated_strings,
    "op4_kd_shards": op4_kd_shards,
    "op5_decontaminate": op5_decontaminate,
    "op6_language": op6_language,
    "op7_additive_search": op7_additive_search,
    "op8_mix_sources": op8_mix_sources,
    "op9_simhash_pivots": op9_simhash_pivots,
    "op10_importance": op10_importance,
}

_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_WORDS = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_ITEM_WORDS = f"regexp_extract_all(translate(text, '{_UP}', '{_LOW}'), '{_WORDS}')"

_OP5 = f"""
WITH t AS (SELECT doc_id, coalesce({_ITEM_WORDS}, []) AS w FROM documents),
b AS (SELECT coalesce(CAST(item_id AS VARCHAR), '') AS item, coalesce({_ITEM_WORDS}, []) AS w FROM benchmark),
iw AS (SELECT item, array_to_string(w[i:i + 9], ' ') AS k, CAST(10 AS BIGINT) AS n FROM (SELECT item, w, unnest(range(1, len(w) - 8)) AS i FROM b WHERE len(w) >= 10)
  UNION SELECT item, array_to_string(w, ' '), CAST(len(w) AS BIGINT) FROM b WHERE len(w) BETWEEN 1 AND 9),
dw AS (SELECT doc_id, p, n, array_to_string(w[p:p + n - 1], ' ') AS k FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM t, (SELECT DISTINCT n FROM iw))),
hit AS (SELECT DISTINCT doc_id, p, n, item FROM dw JOIN iw USING (n, k)),
wh AS (SELECT doc_id, count(DISTINCT x) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS x FROM hit) GROUP BY doc_id),
ih AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS s FROM (SELECT DISTINCT doc_id, item FROM hit) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM t LEFT JOIN wh USING (doc_id) LEFT JOIN ih USING (doc_id)"""

_OP8 = rf"""
WITH sized AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
    md5('mix|' || coalesce(CAST(doc_id AS VARCHAR), '') || '|' || md5(coalesce(text, ''))) AS h FROM documents),
s1 AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS no FROM sized GROUP BY source),
s2 AS (SELECT *, CAST([3, 1, 2][(no - 1) % 3 + 1] AS DOUBLE) AS w, 2 * source_size AS cap, CAST(sum(source_size) OVER () AS DOUBLE) * CAST(1.5 AS DOUBLE) AS total FROM s1),
s3 AS (SELECT *, cap / w AS ratio FROM s2),
s4 AS (SELECT *, sum(cap) OVER u AS caps, sum(w) OVER () - sum(w) OVER u AS rest FROM s3 WINDOW u AS (ORDER BY ratio, no ROWS UNBOUNDED PRECEDING)),
s5 AS (SELECT *, caps + ratio * rest <= total AS is_full FROM s4),
targets AS (SELECT no, source, source_size, CASE WHEN is_full THEN CAST(cap AS DOUBLE)
    ELSE w * (total - coalesce(CAST(sum(cap) FILTER (is_full) OVER () AS DOUBLE), 0)) / sum(w) FILTER (NOT is_full) OVER () END AS target FROM s5),
bounds AS (SELECT no, source_size, CAST(round(target * 1000) AS BIGINT) AS width, sum(CAST(round(target * 1000) AS BIGINT)) OVER (ORDER BY no ROWS UNBOUNDED PRECEDING) AS hi,
    sum(CAST(round(target * 1000) AS BIGINT)) OVER () AS whole FROM targets WHERE target > 0),
points AS (SELECT i, i * CAST({mixing.GOLDEN!r} AS DOUBLE) - floor(i * CAST({mixing.GOLDEN!r} AS DOUBLE)) AS u FROM range(CAST((SELECT ceil(round(sum(target), 3) / {mixing.BLOCK_WORDS}) FROM targets) AS BIGINT)) r(i)),
ranked AS (SELECT no, source_size, row_number() OVER (PARTITION BY no ORDER BY i) - 1 AS r FROM points JOIN bounds ON u * whole >= hi - width AND u * whole < hi),
takes AS (SELECT no, r % ((source_size + {mixing.BLOCK_WORDS - 1}) // {mixing.BLOCK_WORDS}) AS block, count(*) AS takes FROM ranked WHERE r // ((source_size + {mixing.BLOCK_WORDS - 1}) // {mixing.BLOCK_WORDS}) < 2 GROUP BY ALL),
laid AS (SELECT row_number() OVER () AS id, doc_id, size, t.no, source_size, target, CAST(coalesce(sum(size) OVER (PARTITION BY t.no ORDER BY h ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS b
    FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source),
pieces AS (SELECT *, unnest(range(b // {mixing.BLOCK_WORDS}, (b + size - 1) // {mixing.BLOCK_WORDS} + 1)) AS block FROM laid WHERE size > 0),
got AS (SELECT id, CAST(sum((least(b + size, (block + 1) * {mixing.BLOCK_WORDS}) - greatest(b, block * {mixing.BLOCK_WORDS})) * takes) AS BIGINT) AS taken FROM pieces JOIN takes USING (no, block) GROUP BY id)
SELECT doc_id, size, source_size, target, coalesce(taken, 0) AS taken FROM laid LEFT JOIN got USING (id)"""

_OP3 = """
WITH t AS (SELECT row_number() OVER () AS id, doc_id, encode(coalesce(text, '')) AS b FROM documents),
w AS (SELECT id, p, md5_number(b[p:p + 199]) AS k FROM (SELECT id, b, unnest(range(1, octet_length(b) - 198)) AS p FROM t)),
hit AS (SELECT id, p FROM w WHERE k IN (SELECT k FROM w GROUP BY k HAVING count(*) > 1)),
mark AS (SELECT id, p, CASE WHEN p > lag(p) OVER (PARTITION BY id ORDER BY p) + 200 THEN 1 ELSE 0 END AS fresh FROM hit),
part AS (SELECT id, p, sum(fresh) OVER (PARTITION BY id ORDER BY p ROWS UNBOUNDED PRECEDING) AS run FROM mark),
runs AS (SELECT id, min(p) AS a, max(p) + 199 AS z FROM part GROUP BY id, run),
cut AS (SELECT id, a, z, coalesce(lag(z) OVER (PARTITION BY id ORDER BY a), 0) + 1 AS x FROM runs),
ends AS (SELECT id, max(z) AS z, count(*) AS n_spans, sum(z - a + 1) AS n_removed FROM runs GROUP BY id),
gaps AS (SELECT id, x, a - 1 AS y FROM cut UNION ALL SELECT t.id, coalesce(z, 0) + 1, octet_length(b) FROM t LEFT JOIN ends USING (id)),
kept AS (SELECT id, string_agg(CASE WHEN y >= x THEN hex(b[x:y]) ELSE '' END, '' ORDER BY x) AS h FROM gaps JOIN t USING (id) GROUP BY id)
SELECT doc_id, CAST(octet_length(b) AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(h)) AS kept_sha256
FROM t LEFT JOIN ends USING (id) JOIN kept USING (id)"""

_OP7 = """
WITH c AS (SELECT CAST(vec_id AS BIGINT) AS vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL),
ok AS (SELECT * FROM c WHERE len([x for x in v if x IS NULL OR NOT isfinite(x)]) = 0 AND len([x for x in v if x <> 0]) > 0),
used AS (SELECT * FROM ok WHERE len(v) = (SELECT len(v) FROM ok GROUP BY len(v) ORDER BY count(*) DESC, len(v) LIMIT 1)),
q AS (SELECT vec_id AS query_id, min(v) AS q FROM used WHERE vec_id % 20 = 0 GROUP BY vec_id),
near AS (SELECT query_id, vec_id, list_inner_product(q, v) AS score FROM q, used WHERE vec_id <> query_id),
ranked AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM near)
SELECT * FROM ranked WHERE rank <= 20"""

#: SQL for the operators that it can express; the others are tested against brute force.
ORACLE_SQL: dict[str, str] = {"op3_repeated_strings": _OP3, "op5_decontaminate": _OP5, "op7_additive_search": _OP7, "op8_mix_sources": _OP8}
