"""SQL text of every query that SQL can express, for an engine that reads the same tables."""

from __future__ import annotations

import hashlib
import re

from repsum.operators.advisor import RANGE_KEEPS
from repsum.sources.templates import JOINS, ODD_INSTANCES, ODD_TEXTS, ORDER_INSTANCES, PREDICATES, REPORTS, STARS, expected_tokens, odd_tokens, render, statistics

ORDERS = """
lines AS (SELECT l_orderkey AS qid, l_returnflag || l_linestatus AS fn, p_brand AS tb, p_type AS gb
  FROM lineitem LEFT JOIN part ON l_partkey = p_partkey),
sums AS (SELECT l_orderkey AS k,
    sum(CAST(round(l_extendedprice*100) AS BIGINT) * CAST(round(l_tax*100) AS BIGINT)) AS s2,
    sum(CAST(round(l_extendedprice*100) AS BIGINT)) AS s3, sum(CAST(l_quantity AS BIGINT)) AS s4,
    sum(CAST(round(l_extendedprice*100) AS BIGINT) * (100 - CAST(round(l_discount*100) AS BIGINT))) AS s5, count(*) AS s6
  FROM lineitem GROUP BY l_orderkey),
ent AS (SELECT o_orderkey AS qid, o_orderdate AS ts, o_orderpriority AS ob, CAST(round(o_totalprice*100) AS BIGINT) AS n1,
    CAST(coalesce(s2,0) AS BIGINT) AS n2, CAST(coalesce(s3,0) AS BIGINT) AS n3, CAST(coalesce(s4,0) AS BIGINT) AS n4,
    CAST(coalesce(s5,0) AS BIGINT) AS n5, CAST(greatest(coalesce(s6,0)-1,0) AS BIGINT) AS n6
  FROM orders LEFT JOIN sums ON o_orderkey = k),
numv AS (UNPIVOT (SELECT qid, n1, n2, n3, n4, n5, n6 FROM ent) ON n1, n2, n3, n4, n5, n6 INTO NAME feature VALUE v),
edge AS (SELECT feature, min(v) AS lo, max(v) AS hi FROM numv GROUP BY feature),
bags AS (SELECT qid, feature, token, count(*) AS mult FROM (UNPIVOT lines ON fn, tb, gb INTO NAME feature VALUE token) GROUP BY ALL
  UNION ALL SELECT qid, 'ob', ob, 1 FROM ent WHERE ob IS NOT NULL)"""


def orders_tokens(buckets: int = 1000, pinned: dict[str, tuple[int, int]] | None = None) -> str:
    edge = "edge" if pinned is None else "(VALUES " + ", ".join(f"('{f}', CAST({a} AS BIGINT), CAST({b} AS BIGINT))" for f, (a, b) in pinned.items()) + ") AS edge(feature, lo, hi)"
    return f"""{ORDERS},
tok AS (SELECT qid, feature, token, CAST(mult AS BIGINT) AS mult FROM bags UNION ALL
  SELECT qid, numv.feature, CAST(CASE WHEN hi = lo THEN 0 ELSE ((least(greatest(v, lo), hi) - lo) * {buckets}) // (hi - lo) END AS VARCHAR), 1
  FROM numv JOIN {edge} ON numv.feature = edge.feature)"""


EVENTS = """
ev AS (SELECT event_id AS qid, ts, event_type AS t, user_id, epoch_us(ts) AS us, hour(ts) AS h, CAST(round(value*100) AS BIGINT) AS value,
    CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events),
evw AS (SELECT *, lag(t) OVER u AS pt, us // 1000 - lag(us // 1000) OVER u AS gap,
    count(*) OVER (PARTITION BY user_id, CAST(ts AS DATE) ORDER BY us, qid ROWS UNBOUNDED PRECEDING) AS run
  FROM ev WINDOW u AS (PARTITION BY user_id ORDER BY us, qid)),
numv AS (UNPIVOT (SELECT qid, value, k, gap, run FROM evw) ON value, k, gap, run INTO NAME feature VALUE v),
edge AS (SELECT feature, min(v) AS lo, max(v) AS hi FROM numv GROUP BY feature),
bags AS (SELECT qid, 'type' AS feature, t AS token FROM evw UNION ALL SELECT qid, 'bigram', pt || '→' || t FROM evw WHERE pt IS NOT NULL
  UNION ALL SELECT qid, 'hour', CAST(h AS VARCHAR) FROM evw UNION ALL SELECT qid, 'user', CAST(user_id AS VARCHAR) FROM evw),
tok AS (SELECT qid, feature, token, CAST(1 AS BIGINT) AS mult FROM bags UNION ALL
  SELECT qid, numv.feature, CAST(CASE WHEN hi = lo THEN 0 ELSE ((v - lo) * 1000) // (hi - lo) END AS VARCHAR), 1 FROM numv JOIN edge USING (feature))"""

FREQ = """
freq AS (SELECT feature, token, CAST(sum(mult) AS BIGINT) AS freq FROM tok GROUP BY feature, token)"""
SAMPLE = """
samp AS (SELECT qid FROM (SELECT o_orderkey AS qid, row_number() OVER (ORDER BY md5('42|' || o_orderkey), o_orderkey) AS n, count(*) OVER () AS z FROM orders) WHERE n <= floor(sqrt(z)))"""
BOTH = FREQ + """,
sfreq AS (SELECT feature, token, CAST(sum(mult) AS BIGINT) AS ms FROM tok JOIN samp USING (qid) GROUP BY feature, token),
both_ AS (SELECT f.feature, f.token, f.freq AS mw, coalesce(s.ms, 0) AS ms, f.freq / sum(f.freq) OVER () AS d,
    coalesce(s.ms, 0) / sum(coalesce(s.ms, 0)) OVER () AS ps FROM freq f LEFT JOIN sfreq s USING (feature, token))"""


def on_sample(select: str) -> str:
    return f"WITH {orders_tokens()}, {SAMPLE}, {BOTH} {select}"


def greedy(rounds: int, gamma: float | str, key: str = "unit", head: str | None = None, target: str | None = None, budget: float | None = None) -> str:
    """Greedy of fixed depth as a chain: score all, take the best, add it to the counts.

    ``target`` is SQL for (feature, token, d); ``key`` 'unit' or 'size'; with a budget only entries that still fit.
    """
    head = head or orders_tokens()
    d = target or "SELECT feature, token, freq / sum(freq) OVER () AS d FROM freq"
    parts = [
        f"WITH {head}, {FREQ}",
        f"dist AS MATERIALIZED (SELECT row_number() OVER (ORDER BY feature, token) AS tid, feature, token, d FROM ({d}))",
        "vec AS MATERIALIZED (SELECT qid, tid, d, mult FROM tok JOIN dist USING (feature, token))",
        f"cst AS MATERIALIZED (SELECT qid, CAST({'sum(mult)' if key == 'size' else '1'} AS DOUBLE) AS cost FROM vec GROUP BY qid)",
        "m0 AS MATERIALIZED (SELECT tid, CAST(0 AS DOUBLE) AS m FROM dist)",
    ]
    taken = []
    for r in range(1, rounds + 1):
        if gamma == "cover":
            score = "round(sum(CASE WHEN m = 0 THEN d ELSE 0 END), 9) AS g, 0 AS g2"
        elif gamma == "limit":
            score = "round(sum(CASE WHEN m = 0 THEN d ELSE 0 END), 9) AS g, round(sum(CASE WHEN m = 0 THEN d * ln(mult) ELSE d * (ln(m + mult) - ln(m)) END), 9) AS g2"
        else:
            score = f"round(sum(d * (ln(m + mult + {gamma!r}) - ln(m + {gamma!r}))), 9) AS g, 0 AS g2"
        out = " AND ".join([f"qid <> (SELECT qid FROM p{i})" for i in taken]) or "true"
        fits = f" AND cost <= {budget} - ({' + '.join(f'(SELECT cost FROM p{i})' for i in taken) or '0'})" if budget is not None else ""
        parts.append(f"p{r} AS MATERIALIZED (SELECT qid, g, g2, cost FROM (SELECT qid, {score} FROM vec JOIN m{r - 1} USING (tid) GROUP BY qid) JOIN cst USING (qid) WHERE {out}{fits} ORDER BY round(g / cost, 9) DESC, g2 / cost DESC, qid LIMIT 1)")
        parts.append(f"m{r} AS MATERIALIZED (SELECT m{r - 1}.tid, m + coalesce(mult, 0) AS m FROM m{r - 1} LEFT JOIN (SELECT tid, mult FROM vec WHERE qid = (SELECT qid FROM p{r})) x ON m{r - 1}.tid = x.tid)")
        taken.append(r)
    union = " UNION ALL ".join(f"SELECT CAST({r} AS INTEGER) AS pick_no, qid, round(g, 6) AS gain, cost FROM p{r}" for r in taken)
    return ", ".join(parts) + " " + union


def chain(tag: str, rounds: int, gamma: float, only: str) -> list[str]:
    """The rounds of greedy() under other names, over the entries that ``only`` (a condition on qid) admits."""
    parts, taken = [f"{tag}m0 AS MATERIALIZED (SELECT tid, CAST(0 AS DOUBLE) AS m FROM dist)", f"{tag}v AS MATERIALIZED (SELECT * FROM vec WHERE {only})"], []
    for r in range(1, rounds + 1):
        out = " AND ".join([f"qid <> (SELECT qid FROM {tag}p{i})" for i in taken]) or "true"
        parts.append(f"{tag}p{r} AS MATERIALIZED (SELECT qid, g FROM (SELECT qid, round(sum(d * (ln(m + mult + {gamma!r}) - ln(m + {gamma!r}))), 9) AS g FROM {tag}v JOIN {tag}m{r - 1} USING (tid) GROUP BY qid) WHERE {out} ORDER BY g DESC, qid LIMIT 1)")
        parts.append(f"{tag}m{r} AS MATERIALIZED (SELECT a.tid, m + coalesce(mult, 0) AS m FROM {tag}m{r - 1} a LEFT JOIN (SELECT tid, mult FROM {tag}v WHERE qid = (SELECT qid FROM {tag}p{r})) x ON a.tid = x.tid)")
        taken.append(r)
    return parts


def shape_rows(templates) -> tuple[str, str]:
    """(CTEs shapes, tests, grouped of described templates with 100 entries each; CTEs with sizes and distinct values of what they read)."""
    sh = ", ".join(f"('{t.name}', '{x}')" for t in templates for x in t.tables)
    te = ", ".join(f"('{t.name}', '{c}', '{PREDICATES[c].split()[0]}')" for t in templates for c in t.where)
    gr = ", ".join(f"('{t.name}', '{c}')" for t in templates for c in t.group)
    tables = sorted({x for t in templates for x in t.tables})
    columns = sorted({c for t in templates for c in (*t.where, *t.group)})
    sizes = " UNION ALL ".join(f"SELECT '{x}' AS tbl, count(*) AS rows FROM {x}" for x in tables)
    ndv = " UNION ALL ".join(f"SELECT '{c}' AS col, count(DISTINCT {c.split('.')[1]}) AS d FROM {c.split('.')[0]}" for c in columns)
    return (
        f"shapes(shape, tbl) AS (VALUES {sh}), tests(shape, col, by_) AS (VALUES {te}), grouped(shape, col) AS (VALUES {gr})",
        f"sizes AS MATERIALIZED ({sizes}), ndv AS MATERIALIZED ({ndv})",
    )


def structures(templates) -> str:
    """CTEs of every candidate structure: keeps (shape, col, keep), need (shape, col), cand (id, kind, tbl, cols, rows)."""
    described, measured = shape_rows(templates)
    ranges = ", ".join(f"('{b}', {k})" for b, k in RANGE_KEEPS.items())
    return f"""{described}, {measured}, fixed(by_, k) AS (VALUES {ranges}),
      keeps AS MATERIALIZED (SELECT shape, tests.col, string_split(tests.col, '.')[1] AS tbl, coalesce(k, least(1000, greatest(1, 1000 // greatest(1, d)))) AS keep FROM tests JOIN ndv ON tests.col = ndv.col LEFT JOIN fixed USING (by_)),
      need AS (SELECT shape, col FROM tests UNION SELECT shape, col FROM grouped),
      cols AS (SELECT shape, string_agg(col, ',' ORDER BY col) AS cols, list(col ORDER BY col) AS held, CAST(least(product(greatest(1, d)), 1e15) AS BIGINT) AS groups FROM need JOIN ndv USING (col) GROUP BY shape),
      tabs AS (SELECT shape, string_agg(tbl, ',' ORDER BY tbl) AS tbl, max(rows) AS largest FROM shapes JOIN sizes USING (tbl) GROUP BY shape),
      cand AS MATERIALIZED (SELECT DISTINCT 'index' AS kind, tbl, col AS cols, CAST(0 AS BIGINT) AS rows FROM keeps
        UNION SELECT 'view', tbl, cols, least(groups, largest) FROM cols JOIN tabs USING (shape) WHERE shape IN (SELECT shape FROM grouped)),
      usable AS MATERIALIZED (SELECT c.kind, c.tbl, c.cols, c.rows, t.shape FROM cand c JOIN tabs t ON c.kind = 'view' AND c.tbl = t.tbl JOIN cols n ON n.shape = t.shape WHERE len([x for x in n.held if NOT list_contains(string_split(c.cols, ','), x)]) = 0)"""


def spec_rows(templates, instances: int = 100) -> str:
    """(n, feature, token) of the described templates, as VALUES."""
    rows = [(n, f, t) for n, x in enumerate(templates) for f, t in expected_tokens(x)]
    return "(VALUES " + ", ".join(f"({n}, '{f}', '{t}')" for n, f, t in rows) + ") AS spec(n, feature, token)"


def toy() -> str:
    """Scores of every summary of the worked example, from its tokens."""
    rows = [
        (1, "fn", "AVG", 1), (1, "fn", "MAX", 2), (1, "tb", "T1", 1), (1, "gb", "T1.a", 1), (2, "fn", "COUNT", 1), (2, "tb", "T1", 1), (2, "tb", "T2", 1),
        (3, "tb", "T1", 1), (3, "tb", "T2", 1), (3, "tb", "T3", 1), (3, "ob", "T1.a", 1), (3, "ob", "T2.b", 1), (3, "ob", "T3.c", 1),
    ]
    buckets = {1: (0, 6, 0, 0, 0, 0), 2: (10, 0, 3, 10, 5, 5), 3: (6, 10, 10, 4, 10, 10)}
    rows += [(q, f"n{i}", str(b), 1) for q, bs in buckets.items() for i, b in enumerate(bs, 1)]
    values = ", ".join(f"({q}, '{f}', '{t}', {m})" for q, f, t, m in rows)
    sets = ", ".join(f"('{s}', {q})" for s in ("1", "2", "3", "1,2", "1,3", "2,3", "1,2,3") for q in s.split(","))
    return f"""WITH tok(qid, feature, token, mult) AS (VALUES {values}), sets(s, qid) AS (VALUES {sets}),
      w AS (SELECT feature, token, sum(mult) AS mw FROM tok GROUP BY ALL), m AS (SELECT s, feature, token, sum(mult) AS ms FROM sets JOIN tok USING (qid) GROUP BY ALL),
      b AS (SELECT x.s, w.feature, w.token, mw / 32 AS d, coalesce(ms, 0) AS ms FROM (SELECT DISTINCT s FROM sets) x CROSS JOIN w LEFT JOIN m ON m.s = x.s AND m.feature = w.feature AND m.token = w.token),
      c AS (SELECT *, ms / sum(ms) OVER (PARTITION BY s) AS ps FROM b), f AS (SELECT s, feature, count(*) FILTER (ms > 0) / count(*) AS a FROM c GROUP BY ALL)
      SELECT c.s, round((SELECT min(a) FROM f WHERE f.s = c.s), 6) AS alpha_min, round((SELECT avg(a) FROM f WHERE f.s = c.s), 6) AS alpha_avg,
        round(1 - sum(abs(ps - d)) / 2, 6) AS rho_l1, round(1 - max(abs(ps - d)), 6) AS rho_linf, round(sum(d * ln(ms + 1)), 6) AS g FROM c GROUP BY c.s"""


_B = "FROM both_"
UNIFORM = "SELECT feature, token, 1.0 / count(*) OVER () AS d FROM freq"
#: Numeric bounds that stay as batches arrive, and feature weights.
PINNED = {"n1": (100_000, 40_000_000), "n2": (0, 100_000_000), "n3": (0, 100_000_000), "n4": (0, 500), "n5": (0, 10_000_000_000), "n6": (0, 20)}
WEIGHTS = {"fn": 0.25, "tb": 0.25, "gb": 0.1, "ob": 0.1, "n1": 0.05, "n2": 0.05, "n3": 0.05, "n4": 0.05, "n5": 0.05, "n6": 0.05}
WEIGHT_ROWS = "(VALUES " + ", ".join(f"('{f}', CAST({w} AS DOUBLE))" for f, w in WEIGHTS.items()) + ") AS wt(feature, w)"
GAMMAS = (1.0, 0.1, 0.001, 1e-06, 1e-10, 1e-15, 1e-20, 1e-25)
BETAS = (0.0, 0.25, 0.5, 0.75, 1.0)

SCORES = f"SELECT (SELECT min(a) FROM (SELECT feature, count(*) FILTER (ms > 0) / count(*) AS a {_B} GROUP BY feature)) AS alpha_min, (SELECT avg(a) FROM (SELECT feature, count(*) FILTER (ms > 0) / count(*) AS a {_B} GROUP BY feature)) AS alpha_avg, 1 - sum(abs(ps - d)) / 2 AS rho_l1, 1 - max(abs(ps - d)) AS rho_linf {_B}"
BY_FEATURE = f"SELECT feature, count(*) FILTER (ms > 0) / count(*) AS alpha, 1 - sum(abs(ms / zs - d / zd)) / 2 AS rho_l1, 1 - max(abs(ms / zs - d / zd)) AS rho_linf FROM (SELECT *, sum(ms) OVER (PARTITION BY feature) AS zs, sum(d) OVER (PARTITION BY feature) AS zd {_B}) GROUP BY feature"


def _batch_tokens(n: int) -> str:
    return f"{EVENTS}, bt AS (SELECT qid, ntile({n}) OVER (ORDER BY ts, qid) AS batch FROM ev)"


def oracle() -> dict[str, str]:
    o: dict[str, str] = {}
    tok = f"WITH {orders_tokens()} "
    o["w_orders_tokens"] = tok + "SELECT * FROM tok"
    o["w_orders_numeric"] = f"WITH {ORDERS} SELECT qid, n1, n2, n3, n4, n5, n6 FROM ent"
    o["w_events_tokens"] = f"WITH {EVENTS} SELECT * FROM tok"
    o["w_docs_tokens"] = """WITH w AS (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS token FROM documents),
      t AS (SELECT 'word' AS feature, token FROM w UNION ALL SELECT 'lang', lang FROM documents UNION ALL SELECT 'source', source FROM documents)
      SELECT feature, count(DISTINCT token) AS tokens, count(*) AS occurrences, CASE WHEN count(DISTINCT token) > 100000 THEN 'drop or weigh down' WHEN count(DISTINCT token) = 1 THEN 'constant' ELSE 'keep' END AS advice FROM t WHERE token IS NOT NULL GROUP BY feature"""
    o["w_conv_tokens"] = """WITH t AS (SELECT conv_id AS qid, role, lower(substr(text, 1, 1)) AS c FROM conversations)
      SELECT qid, 'role' AS feature, role AS token, count(*) AS mult FROM t WHERE role IS NOT NULL GROUP BY ALL UNION ALL
      SELECT qid, 'opening', CASE WHEN regexp_matches(c, '^[aeiou]') THEN 'vowel' WHEN regexp_matches(c, '^[a-z]') THEN 'consonant' ELSE 'other' END AS k, count(*) FROM t GROUP BY qid, k"""
    o["w_pages_tokens"] = r"""WITH p AS (SELECT page_id AS qid, regexp_extract(url, '^https?://([^/?#]*)', 1) AS host, regexp_extract(url, '^https?://[^/?#]*([^?#]*)', 1) AS path, regexp_extract(url, '\?([^#]*)', 1) AS query, html FROM pages),
      t AS (SELECT qid, 'host' AS feature, host AS token FROM p UNION ALL SELECT qid, 'segment', s FROM (SELECT qid, unnest(string_split(path, '/')) AS s FROM p) WHERE s <> ''
      UNION ALL SELECT qid, 'key', string_split(s, '=')[1] FROM (SELECT qid, unnest(string_split(query, '&')) AS s FROM p) WHERE s <> ''
      UNION ALL SELECT qid, 'tag', unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) FROM p)
      SELECT qid, feature, token, count(*) AS mult FROM t GROUP BY ALL"""
    dealt = lambda n, m: f"(SELECT o_orderkey AS qid, o_orderkey % {n} AS n, coalesce(o_custkey, 0) % {m} AS i FROM orders WHERE o_orderkey IS NOT NULL) AS dealt"
    for name, templates in (("w_sql_tokens", REPORTS), ("w_star_tokens", STARS)):
        o[name] = f"SELECT qid, feature, token, count(*) AS mult FROM {spec_rows(templates)} JOIN {dealt(len(templates), ORDER_INSTANCES)} USING (n) GROUP BY ALL"
    o["w_sql_odd_tokens"] = "SELECT qid, feature, token, count(*) AS mult FROM (VALUES " + ", ".join(f"({n}, '{f}', '{t}')" for n, (_, x) in enumerate(ODD_TEXTS) for f, t in odd_tokens(x)) + f") AS spec(n, feature, token) JOIN {dealt(len(ODD_TEXTS), ODD_INSTANCES)} USING (n) GROUP BY ALL"
    o["w_sql_mix_tokens"] = f"WITH c AS (SELECT i % {len(REPORTS + STARS)} AS n, count(*) AS z FROM range((SELECT count(*) FROM orders)) r(i) GROUP BY ALL) SELECT feature, token, CAST(sum(z) AS BIGINT) AS freq FROM {spec_rows(REPORTS + STARS)} JOIN c USING (n) GROUP BY feature, token"
    joined = lambda t: [c.strip() for k, a in enumerate(t.tables) for b in t.tables[k + 1 :] for c in (JOINS.get((a, b)) or JOINS.get((b, a)) or "").split("=") if c]
    o["w_sql_where"] = "SELECT token, count(*) AS freq FROM (VALUES " + ", ".join(f"({n}, '{c}')" for n, t in enumerate(STARS) for c in (*joined(t), *t.where)) + f") AS w(n, token) JOIN {dealt(len(STARS), ORDER_INSTANCES)} USING (n) GROUP BY token"
    drawn = ", ".join(f"({n}, {i}, '{t.name}', '{hashlib.md5(render(t, i).encode()).hexdigest()}', {statistics(t, i)[0]}, {len(t.tables) - 1})" for n, t in enumerate(REPORTS) for i in range(ORDER_INSTANCES))
    o["w_sql_statistics"] = f"SELECT template, count(DISTINCT text) AS texts, count(DISTINCT ms) AS times, CAST(min(j) AS BIGINT) AS n_joins FROM (VALUES {drawn}) AS v(n, i, template, text, ms, j) JOIN {dealt(len(REPORTS), ORDER_INSTANCES)} USING (n, i) GROUP BY template"
    bare = lambda t: re.sub(r"'[^']*'|0\.0\d|(?<=[=<>] )\d+", "?", render(t, 0))
    o["w_sql_fingerprints"] = "SELECT template, fingerprint, count(*) AS n FROM (VALUES " + ", ".join(f"({n}, '{t.name}', '{bare(t)}')" for n, t in enumerate(REPORTS + STARS)) + f") AS v(n, template, fingerprint) JOIN {dealt(len(REPORTS + STARS), ORDER_INSTANCES)} USING (n) GROUP BY template, fingerprint"
    o["doc_words"] = "WITH t AS (SELECT 'word' AS feature, unnest(string_split(lower(text), ' ')) AS token FROM documents UNION ALL SELECT 'lang', lang FROM documents UNION ALL SELECT 'source', source FROM documents) SELECT feature, token, count(*) AS freq FROM t WHERE token IS NOT NULL GROUP BY ALL"
    o["token_map"] = tok + "SELECT qid, CAST(coalesce(sum(mult) FILTER (feature = 'fn'), 0) AS BIGINT) AS fn, CAST(coalesce(sum(mult) FILTER (feature = 'tb'), 0) AS BIGINT) AS tb, CAST(coalesce(sum(mult) FILTER (feature = 'ob'), 0) AS BIGINT) AS ob, CAST(count(DISTINCT feature) AS INTEGER) AS features FROM tok GROUP BY qid"
    o["w_sql_joins"] = "SELECT qid, CAST(j AS BIGINT) AS n_joins FROM (VALUES " + ", ".join(f"({n}, {len(t.tables) - 1})" for n, t in enumerate(REPORTS)) + f") AS v(n, j) JOIN {dealt(len(REPORTS), ORDER_INSTANCES)} USING (n)"
    o["bounds"] = f"WITH {ORDERS} SELECT feature, lo, hi FROM edge"
    for h in (10, 1000):
        o[f"buckets_h{h}"] = f"WITH {orders_tokens(h)} SELECT feature, token, count(*) AS n FROM tok WHERE feature LIKE 'n%' GROUP BY ALL"
    o["buckets_pinned"] = f"WITH {orders_tokens(1000, PINNED)} SELECT feature, token, count(*) AS n FROM tok WHERE feature LIKE 'n%' GROUP BY ALL"
    o["out_of_range"] = f"WITH {ORDERS} SELECT feature, count(*) FILTER (v < lo) AS below, count(*) FILTER (v > hi) AS above, count(*) FILTER (v IS NULL) AS missing FROM numv JOIN (VALUES " + ", ".join(f"('{f}', CAST({a} AS BIGINT), CAST({b} AS BIGINT))" for f, (a, b) in PINNED.items()) + ") AS pin(feature, lo, hi) USING (feature) GROUP BY feature"
    o["token_freq"] = f"WITH {orders_tokens()}, {FREQ} SELECT feature, token, freq, round(freq / sum(freq) OVER (), 9) AS p FROM freq"
    o["domain_sizes"] = f"WITH {orders_tokens()}, {FREQ} SELECT feature, count(*) AS tokens, CAST(sum(freq) AS BIGINT) AS occurrences FROM freq GROUP BY feature"
    o["query_sizes"] = tok + "SELECT qid, CAST(sum(mult) AS BIGINT) AS size FROM tok GROUP BY qid"
    o["packed_vectors"] = f"WITH {orders_tokens()}, {FREQ}, dom AS (SELECT row_number() OVER (ORDER BY feature, token) - 1 AS tid, feature, token FROM freq) SELECT qid, string_agg(tid || ':' || mult, ',' ORDER BY tid) AS vec FROM tok JOIN dom USING (feature, token) GROUP BY qid"
    o["cross_feature"] = tok + "SELECT a.qid, 'fn×ob' AS feature, a.token || '×' || b.token AS token, CAST(sum(a.mult * b.mult) AS BIGINT) AS mult FROM tok a JOIN tok b ON a.qid = b.qid AND a.feature = 'fn' AND b.feature = 'ob' GROUP BY ALL"
    o["feature_corr"] = f"WITH {ORDERS} SELECT x.a, x.b, round(x.r, 6) AS r FROM (SELECT " + ", ".join(f"corr(n{i}, n{j}) AS c{i}{j}" for i in range(1, 7) for j in range(i + 1, 7)) + " FROM ent), LATERAL (VALUES " + ", ".join(f"('n{i}', 'n{j}', c{i}{j})" for i in range(1, 7) for j in range(i + 1, 7)) + ") AS x(a, b, r)"
    o["cramers_v"] = "WITH j AS (SELECT o_orderstatus AS a, o_orderpriority AS b, count(*) AS n FROM orders GROUP BY ALL), m AS (SELECT *, sum(n) OVER (PARTITION BY a) AS na, sum(n) OVER (PARTITION BY b) AS nb FROM j) SELECT 'o_orderstatus' AS a, 'o_orderpriority' AS b, round(sqrt(greatest(sum(n * n / (na * nb)) - 1, 0) / (least(count(DISTINCT a), count(DISTINCT b)) - 1)), 6) AS v FROM m"
    o["inverse_domain_weights"] = f"WITH {orders_tokens()}, {FREQ} SELECT feature, round(x / sum(x) OVER (), 9) AS w FROM (SELECT feature, 1 / count(*) AS x FROM freq GROUP BY feature)"
    # measures of the seeded sample of sqrt(n) entries
    o["coverage_by_feature"] = on_sample(f"SELECT feature, round(count(*) FILTER (ms > 0) / count(*), 6) AS alpha {_B} GROUP BY feature")
    o["coverage_min_avg"] = on_sample(f"SELECT round(alpha_min, 6) AS alpha_min, round(alpha_avg, 6) AS alpha_avg FROM ({SCORES})")
    o["rho_l1"] = on_sample(f"SELECT round(rho_l1, 6) AS rho_l1 FROM ({SCORES})")
    o["rho_linf"] = on_sample(f"SELECT round(rho_linf, 6) AS rho_linf FROM ({SCORES})")
    o["scores_by_feature"] = on_sample(f"SELECT feature, round(alpha, 6) AS alpha, round(rho_l1, 6) AS rho_l1, round(rho_linf, 6) AS rho_linf FROM ({BY_FEATURE})")
    o["scores_weighted"] = on_sample(f"SELECT round(sum(w * alpha), 6) AS alpha_w, round(sum(w * rho_l1), 6) AS rho_w FROM ({BY_FEATURE}) JOIN {WEIGHT_ROWS} USING (feature)")
    o["scores_custom_target"] = on_sample(f"SELECT round(1 - sum(abs(ps - 1.0 / z)) / 2, 6) AS rho_l1, round(1 - max(abs(ps - 1.0 / z)), 6) AS rho_linf FROM (SELECT *, count(*) OVER () AS z {_B})")
    grid = " UNION ALL ".join(f"SELECT CAST({b} AS DOUBLE) AS beta" for b in BETAS)
    mix = lambda a, r: f"round(beta * {a} + (1 - beta) * {r}, 6)"
    o["blend_grid"] = on_sample(f"SELECT beta, {mix('alpha_min', 'rho_l1')} AS min_l1, {mix('alpha_min', 'rho_linf')} AS min_linf, {mix('alpha_avg', 'rho_l1')} AS avg_l1, {mix('alpha_avg', 'rho_linf')} AS avg_linf FROM ({SCORES}), ({grid})")
    o["compression_ratio"] = f"WITH {orders_tokens()}, {SAMPLE}, c AS (SELECT qid, sum(mult) AS cost FROM tok GROUP BY qid) SELECT round(1 - sum(cost) FILTER (qid IN (SELECT qid FROM samp)) / sum(cost), 6) AS eta FROM c"
    o["objective_gamma_grid"] = on_sample(" UNION ALL ".join(f"SELECT CAST({g!r} AS DOUBLE) AS gamma, round(sum(CASE WHEN ms > 0 THEN d * (ln(ms + {g!r}) - ln({g!r})) ELSE 0 END), 6) AS g {_B}" for g in GAMMAS))
    o["objective_limit"] = on_sample(f"SELECT round(sum(CASE WHEN ms > 0 THEN d ELSE 0 END), 6) AS covered, round(sum(CASE WHEN ms > 0 THEN d * ln(ms) ELSE 0 END), 6) AS log_part {_B}")
    o["kl_entropy"] = on_sample(f"SELECT round(sum(d * (ln(d) - ln((ms + 0.001) / z))), 6) AS kl, round(sum(-d * ln(d)), 6) AS entropy FROM (SELECT *, sum(ms + 0.001) OVER () AS z {_B})")
    o["uncovered_tokens"] = on_sample(f"SELECT feature, token, mw AS freq {_B} WHERE ms = 0")
    # the compressor, eight rounds
    o["greedy_unit_8"] = o["greedy_fenced_eq_eager"] = greedy(8, 1e-25)
    o["greedy_gamma1_8"] = greedy(8, 1.0)
    o["greedy_limit_8"] = greedy(8, "limit")
    o["greedy_knapsack_8"] = greedy(8, 1e-25, "size", budget=200)
    o["greedy_weighted_8"] = greedy(8, 1e-25, target=f"SELECT feature, token, w * 10 * freq / sum(freq) OVER () AS d FROM freq JOIN {WEIGHT_ROWS} USING (feature)")
    o["greedy_target_8"] = greedy(8, 1e-25, target=UNIFORM)
    o["testgen_uniform_8"] = greedy(8, 1e-25, target="SELECT feature, token, 1.0 / (count(*) OVER (PARTITION BY feature) * (SELECT count(DISTINCT feature) FROM freq)) AS d FROM freq")
    o["greedy_collapsed_8"] = o["greedy_by_join_8"] = o["greedy_unit_8"]
    o["greedy_safeguard"] = greedy(1, 1e-25).replace("round(g, 6) AS gain, cost FROM", "round(g, 6) AS gain, CAST(100 AS DOUBLE) AS cost FROM")
    numbers = orders_tokens().replace("tok AS (", "every AS (", 1) + ", tok AS (SELECT * FROM every WHERE feature IN ('n1', 'n2', 'n3', 'n4', 'n5', 'n6'))"
    o["platform_choice"] = greedy(8, 1e-25, head=numbers)
    scored = greedy(8, 1e-25).rsplit(" SELECT CAST(1 AS INTEGER)", 1)[0]
    step = lambda r: f"SELECT CAST({r} AS INTEGER) AS pick_no, feature, d, m FROM m{r} JOIN dist USING (tid)"
    picks = " UNION ALL ".join(f"SELECT CAST({r} AS INTEGER) AS pick_no, qid, round(g, 6) AS gain, cost FROM p{r}" for r in range(1, 9))
    o["greedy_trace_8"] = f"""{scored}, steps AS MATERIALIZED ({' UNION ALL '.join(map(step, range(1, 9)))}), picked AS ({picks}),
      al AS (SELECT pick_no, min(a) AS alpha_min, avg(a) AS alpha_avg FROM (SELECT pick_no, feature, count(*) FILTER (m > 0) / count(*) AS a FROM steps GROUP BY ALL) GROUP BY pick_no),
      rh AS (SELECT pick_no, sum(CASE WHEN m > 0 THEN d * (ln(m + 1e-25) - ln(1e-25)) ELSE 0 END) AS g, 1 - sum(abs(m / z - d)) / 2 AS rho_l1, 1 - max(abs(m / z - d)) AS rho_linf FROM (SELECT *, sum(m) OVER (PARTITION BY pick_no) AS z FROM steps) GROUP BY pick_no)
      SELECT pick_no, qid, gain, cost, round(g, 6) AS g, round(alpha_min, 6) AS alpha_min, round(alpha_avg, 6) AS alpha_avg, round(rho_l1, 6) AS rho_l1, round(rho_linf, 6) AS rho_linf, round(0.5 * alpha_avg + 0.5 * rho_l1, 6) AS score FROM picked JOIN al USING (pick_no) JOIN rh USING (pick_no)"""
    o["feature_scores_8"] = f"""{scored}, last AS (SELECT feature, d, m, sum(m) OVER (PARTITION BY feature) AS zm, sum(d) OVER (PARTITION BY feature) AS zd FROM m8 JOIN dist USING (tid))
      SELECT feature, round(count(*) FILTER (m > 0) / count(*), 6) AS alpha, round(1 - sum(abs(m / zm - d / zd)) / 2, 6) AS rho_l1 FROM last GROUP BY feature"""
    o["testgen_boosted"] = greedy(8, 1e-25, target="SELECT feature, token, x / sum(x) OVER () AS d FROM (SELECT feature, token, freq / sum(freq) OVER () * CASE WHEN feature = 'ob' THEN 20.0 ELSE 1.0 END AS x FROM freq)")
    o["greedy_events_8"] = greedy(8, 1e-25, head=EVENTS)
    o["greedy_best_singleton"] = greedy(1, 1e-25)
    o["max_cover_8"] = greedy(8, "cover", target="SELECT feature, token, CAST(1 AS DOUBLE) AS d FROM freq").replace("round(g, 6) AS gain, cost", "CAST(round(g) AS BIGINT) AS new_tokens")
    part = "parts AS (SELECT o_orderkey AS qid, CAST(('0x' || substr(md5('42|' || o_orderkey), 1, 8)) AS BIGINT) % 3 AS part FROM orders)"
    o["partition_sizes"] = f"WITH {part} SELECT CAST(part AS INTEGER) AS part, count(*) AS n FROM parts GROUP BY part"
    for k in range(3):
        sub = greedy(3, 1e-25).replace("FROM vec JOIN m", f"FROM (SELECT * FROM vec WHERE qid IN (SELECT qid FROM parts WHERE part = {k})) vec JOIN m")
        o[f"partition_{k}_picks"] = sub.replace("WITH ", f"WITH {part}, ", 1)
    start = greedy(0, 1e-25).strip()
    local = [x for k in range(3) for x in chain(f"a{k}_", 4, 1e-25, f"qid IN (SELECT qid FROM parts WHERE part = {k})")]
    union = " UNION ALL ".join(f"SELECT qid FROM a{k}_p{r}" for k in range(3) for r in range(1, 5))
    merged = chain("b_", 4, 1e-25, f"qid IN ({union})")
    sets = " UNION ALL ".join(f"SELECT {w} AS w, CAST({r} AS INTEGER) AS pick_no, qid, g FROM {tag}p{r}" for w, tag in enumerate(("b_", "a0_", "a1_", "a2_")) for r in range(1, 5))
    o["partition_merge_4"] = ", ".join([start.replace("WITH ", f"WITH {part}, ", 1), *local, *merged]) + f", sets AS ({sets}) SELECT pick_no, qid, round(g, 6) AS gain, CAST(1 AS DOUBLE) AS cost FROM sets WHERE w = (SELECT w FROM sets GROUP BY w ORDER BY sum(g) DESC, w LIMIT 1)"
    # batches of the events log
    o["batch_ntile"] = f"WITH {_batch_tokens(7)} SELECT CAST(batch AS INTEGER) AS batch, count(*) AS n, min(qid) AS first_qid, max(qid) AS last_qid FROM bt GROUP BY batch"
    o["running_target"] = f"WITH {_batch_tokens(7)}, per AS (SELECT batch, feature, token, sum(mult) AS f FROM tok JOIN bt USING (qid) GROUP BY ALL) SELECT CAST(b.batch AS INTEGER) AS batch, feature, token, CAST(sum(f) AS BIGINT) AS freq FROM per JOIN (SELECT DISTINCT batch FROM bt) b ON per.batch <= b.batch GROUP BY ALL"
    o["merge_append"] = f"WITH {_batch_tokens(7)} SELECT feature, token, CAST(sum(mult) AS BIGINT) AS freq FROM tok JOIN bt USING (qid) GROUP BY ALL"
    o["drift_tv"] = f"""WITH {EVENTS}, dy AS (SELECT CAST(ts AS DATE) AS day, feature, token, sum(mult) AS f FROM tok JOIN ev USING (qid) WHERE feature IN ('type', 'bigram', 'hour', 'user') GROUP BY ALL),
      sh AS (SELECT day, feature, token, f / sum(f) OVER (PARTITION BY day) AS p FROM dy), ds AS (SELECT day, lag(day) OVER (ORDER BY day) AS before FROM (SELECT DISTINCT day FROM dy))
      SELECT day, round(sum(abs(coalesce(p, 0) - coalesce(p0, 0))) / 2, 6) AS tv, count(*) FILTER (p0 IS NULL) AS n_new, count(*) FILTER (p IS NULL) AS n_gone FROM
      (SELECT coalesce(a.day, b.day) AS day, a.p, b.p0 FROM (SELECT sh.day, feature, token, p FROM sh JOIN ds ON sh.day = ds.day WHERE before IS NOT NULL) a
       FULL JOIN (SELECT ds.day, feature, token, p AS p0 FROM sh JOIN ds ON sh.day = ds.before) b ON a.day = b.day AND a.feature = b.feature AND a.token = b.token) GROUP BY day"""
    side = lambda tag, s, w: f"""{tag}w AS (SELECT feature, token, sum(mult) AS mw FROM {w} GROUP BY ALL), {tag}s AS (SELECT feature, token, sum(mult) AS ms FROM {s} GROUP BY ALL),
      {tag} AS (SELECT (SELECT min(a) FROM (SELECT feature, count(ms) / count(*) AS a FROM {tag}w LEFT JOIN {tag}s USING (feature, token) GROUP BY feature)) AS alpha,
        (SELECT 1 - max(abs(coalesce(ms, 0) / zs - mw / zw)) FROM (SELECT *, sum(ms) OVER () AS zs, sum(mw) OVER () AS zw FROM {tag}w LEFT JOIN {tag}s USING (feature, token))) AS rho,
        (SELECT sum(ms) FROM {tag}s) AS s, (SELECT sum(mw) FROM {tag}w) AS w)"""  # noqa: E731
    o["merge_bounds"] = f"""WITH {_batch_tokens(2)}, tb AS MATERIALIZED (SELECT tok.*, batch FROM tok JOIN bt USING (qid)),
      pk AS MATERIALIZED (SELECT qid FROM (SELECT DISTINCT qid, batch FROM tb) QUALIFY row_number() OVER (PARTITION BY batch ORDER BY md5('42|' || qid), qid) <= 50),
      {side("x", "(SELECT * FROM tb WHERE batch = 1 AND qid IN (FROM pk))", "(SELECT * FROM tb WHERE batch = 1)")},
      {side("y", "(SELECT * FROM tb WHERE batch = 2 AND qid IN (FROM pk))", "(SELECT * FROM tb WHERE batch = 2)")},
      {side("u", "(SELECT * FROM tb WHERE qid IN (FROM pk))", "tb")}
      SELECT round(x.alpha, 6) AS alpha_a, round(x.rho, 6) AS rho_a, round(y.alpha, 6) AS alpha_b, round(y.rho, 6) AS rho_b, round(u.alpha, 6) AS alpha_ab, round(u.rho, 6) AS rho_ab,
        round(least(x.alpha, y.alpha) / 2, 6) AS alpha_bound, round(least(x.rho, y.rho), 6) AS rho_bound, x.s * y.w = y.s * x.w AS proportional FROM x, y, u"""
    # baselines
    o["gains_by_join"] = f"WITH {orders_tokens()}, {FREQ}, dist AS (SELECT feature, token, freq / sum(freq) OVER () AS d FROM freq) SELECT qid, round(sum(d * (ln(mult + 1e-25) - ln(1e-25))), 6) AS gain FROM tok JOIN dist USING (feature, token) GROUP BY qid"
    o["toy_scores"] = toy()
    o["exhaustive_toy"] = f"SELECT CAST(len(string_split(s, ',')) AS INTEGER) AS k, s, g FROM ({toy()}) QUALIFY row_number() OVER (PARTITION BY len(string_split(s, ',')) ORDER BY g DESC, s DESC) = 1"
    cand = f"WITH {structures(STARS)}"
    o["index_candidates"] = f"{cand} SELECT kind, tbl, cols, rows FROM cand"
    plain = "plain AS (SELECT shape, sum(rows) AS rows FROM shapes JOIN sizes USING (tbl) GROUP BY shape)"
    o["whatif_cost"] = f"""{cand}, {plain}, none AS (SELECT 100 * sum(rows) AS none FROM plain),
      gone AS (SELECT 'index' AS kind, tbl, col AS cols, sum(100 * (rows - rows * keep // 1000)) AS saved FROM keeps JOIN sizes USING (tbl) GROUP BY ALL
        UNION ALL SELECT 'view', u.tbl, u.cols, sum(100 * greatest(0, p.rows - u.rows)) FROM usable u JOIN plain p USING (shape) GROUP BY ALL)
      SELECT kind, tbl, cols, CAST(none - saved AS BIGINT) AS cost FROM gone, none"""
    rounds = ["cur0 AS MATERIALIZED (SELECT shape, tbl, rows FROM shapes JOIN sizes USING (tbl))", "vis0 AS MATERIALIZED (SELECT DISTINCT shape, CAST(4e18 AS BIGINT) AS v FROM shapes)"]
    for r in range(1, 5):
        done = " AND ".join(f"(kind, tbl, cols) <> (SELECT (kind, tbl, cols) FROM s{i})" for i in range(1, r)) or "true"
        rounds += [
            f"t{r} AS (SELECT c.kind, c.tbl, c.cols, x.shape, sum(least(x.rows, CASE WHEN k.keep IS NULL THEN x.rows ELSE z.rows * k.keep // 1000 END)) AS rows FROM cand c CROSS JOIN cur{r - 1} x JOIN sizes z ON z.tbl = x.tbl LEFT JOIN keeps k ON c.kind = 'index' AND k.shape = x.shape AND k.col = c.cols AND x.tbl = c.tbl GROUP BY ALL)",
            f"s{r} AS MATERIALIZED (SELECT t.kind, t.tbl, t.cols, sum(100 * least(t.rows, v.v, coalesce(u.rows, t.rows))) AS cost FROM t{r} t JOIN vis{r - 1} v USING (shape) LEFT JOIN usable u ON u.kind = t.kind AND u.tbl = t.tbl AND u.cols = t.cols AND u.shape = t.shape WHERE {done.replace('kind, tbl, cols) <>', 't.kind, t.tbl, t.cols) <>')} GROUP BY ALL ORDER BY cost, t.kind, t.tbl, t.cols LIMIT 1)",
            f"cur{r} AS MATERIALIZED (SELECT x.shape, x.tbl, least(x.rows, CASE WHEN k.keep IS NULL THEN x.rows ELSE z.rows * k.keep // 1000 END) AS rows FROM cur{r - 1} x JOIN sizes z ON z.tbl = x.tbl LEFT JOIN (SELECT keeps.* FROM keeps JOIN s{r} ON s{r}.kind = 'index' AND s{r}.cols = keeps.col) k ON k.shape = x.shape AND k.tbl = x.tbl)",
            f"vis{r} AS MATERIALIZED (SELECT v.shape, least(v.v, coalesce(u.rows, v.v)) AS v FROM vis{r - 1} v LEFT JOIN (SELECT usable.* FROM usable JOIN s{r} USING (kind, tbl, cols)) u USING (shape))",
        ]
    o["advise_greedy_4"] = ", ".join([cand, *rounds]) + " " + " UNION ALL ".join(f"SELECT CAST({r} AS INTEGER) AS pick_no, kind, tbl, cols, CAST(cost AS BIGINT) AS cost FROM s{r}" for r in range(1, 5))
    points = """t AS (SELECT conv_id AS qid, role, lower(substr(text, 1, 1)) AS c, length(text) AS l FROM conversations),
      n AS (SELECT qid, count(*) AS turns, sum(l) AS chars FROM t GROUP BY qid), e AS (SELECT min(turns) AS a, max(turns) AS b, min(chars) AS c, max(chars) AS d FROM n),
      num AS (SELECT qid, CASE WHEN b > a THEN (turns - a) / (b - a) ELSE 0 END AS x, CASE WHEN d > c THEN (chars - c) / (d - c) ELSE 0 END AS y FROM n, e),
      tk AS (SELECT qid, 'role=' || role AS k FROM t WHERE role IS NOT NULL UNION SELECT qid, 'opening=' || CASE WHEN regexp_matches(c, '^[aeiou]') THEN 'vowel' WHEN regexp_matches(c, '^[a-z]') THEN 'consonant' ELSE 'other' END FROM t),
      pt AS (SELECT qid, x, y, coalesce(ks, []) AS ks FROM num LEFT JOIN (SELECT qid, list(k) AS ks FROM tk GROUP BY qid) USING (qid))"""
    o["mixed_to_chosen"] = f"""WITH {points}, few AS (SELECT * FROM pt ORDER BY md5('42|' || qid), qid LIMIT 8)
      SELECT p.qid, f.qid AS other, round((sqrt(((p.x - f.x) * (p.x - f.x) + (p.y - f.y) * (p.y - f.y)) / 2) + CASE WHEN len(list_distinct(p.ks || f.ks)) = 0 THEN 0 ELSE 1 - len(list_intersect(p.ks, f.ks)) / len(list_distinct(p.ks || f.ks)) END) / 2, 6) AS dist FROM pt p, few f"""
    o["random_sample"] = "SELECT CAST(n AS INTEGER) AS pick_no, qid FROM (SELECT o_orderkey AS qid, row_number() OVER (ORDER BY md5('42|' || o_orderkey), o_orderkey) AS n FROM orders) WHERE n <= 100"
    o["sample_knapsack"] = tok + ", c AS (SELECT qid, CAST(sum(mult) AS BIGINT) AS cost FROM tok GROUP BY qid) SELECT CAST(n AS INTEGER) AS pick_no, qid, cost FROM (SELECT qid, cost, row_number() OVER w AS n, sum(cost) OVER (w ROWS UNBOUNDED PRECEDING) AS spent FROM c WINDOW w AS (ORDER BY md5('42|' || qid), qid)) WHERE spent <= 1000"
    ks = (10, 25, 50, 100)
    curve = " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS k, count(DISTINCT token || '|' || feature) AS covered, CAST(sum(mult) AS BIGINT) AS tokens FROM tok JOIN (SELECT o_orderkey AS qid, row_number() OVER (ORDER BY md5('42|' || o_orderkey), o_orderkey) AS n FROM orders) USING (qid) WHERE n <= {k}" for k in ks)
    o["sampling_curve"] = tok + curve
    o["top_frequency"] = """WITH v AS (SELECT text, min(doc_id) AS qid, count(*) AS n FROM documents GROUP BY text) SELECT CAST(row_number() OVER (ORDER BY n DESC, qid) AS INTEGER) AS pick_no, qid, n FROM v ORDER BY n DESC, qid LIMIT 20"""
    dist = "sqrt(list_sum(list_transform(list_zip(a.num, b.num), lambda x: (x[1] - x[2]) * (x[1] - x[2]))) / 64)"
    emb = "e AS (SELECT vec_id AS qid, CAST(embedding AS DOUBLE[]) AS num FROM embeddings)"
    near = f"SELECT a.qid, b.qid AS medoid, round({dist}, 9) AS dist FROM e a, e b WHERE b.qid < 8 QUALIFY row_number() OVER (PARTITION BY a.qid ORDER BY round({dist}, 9), b.qid) = 1"
    o["medoid_assign"] = f"WITH {emb} SELECT qid, medoid, round(dist, 6) AS dist FROM ({near})"
    o["medoid_update_1"] = f"WITH {emb}, n AS ({near}), s AS (SELECT n.medoid, a.qid, round(sum({dist}), 6) AS s FROM n JOIN e a ON n.qid = a.qid JOIN n n2 ON n2.medoid = n.medoid JOIN e b ON b.qid = n2.qid GROUP BY ALL) SELECT medoid, qid AS \"new\" FROM s QUALIFY row_number() OVER (PARTITION BY medoid ORDER BY s, qid) = 1"
    chosen = lambda source: f"few AS (SELECT qid FROM {source} ORDER BY md5('42|' || qid), qid LIMIT 8)"
    o["euclid_to_chosen"] = f"WITH {emb}, {chosen('e')} SELECT a.qid, b.qid AS other, round({dist}, 6) AS dist FROM e a, e b WHERE b.qid IN (FROM few)"
    o["jaccard_to_chosen"] = tok + f", {chosen('ent')}, s AS (SELECT DISTINCT qid, feature || '=' || token AS t FROM tok), z AS (SELECT ent.qid, count(t) AS n FROM ent LEFT JOIN s USING (qid) GROUP BY ent.qid), both_ AS (SELECT x.qid, y.qid AS other, count(*) AS i FROM s x JOIN s y ON x.t = y.t WHERE y.qid IN (FROM few) GROUP BY ALL) SELECT a.qid, b.qid AS other, round(CASE WHEN a.n + b.n = 0 THEN 0 ELSE 1 - coalesce(i, 0) / (a.n + b.n - coalesce(i, 0)) END, 6) AS dist FROM z a JOIN z b ON b.qid IN (FROM few) LEFT JOIN both_ ON both_.qid = a.qid AND both_.other = b.qid"
    # relational surface
    o["sql_surface"] = tok + "SELECT CAST(CASE WHEN hi = lo THEN 0 ELSE ((n1 - lo) * 10) // (hi - lo) END AS BIGINT) AS bucket, feature, CAST(sum(mult) AS BIGINT) AS n FROM ent JOIN tok USING (qid), (SELECT min(n1) AS lo, max(n1) AS hi FROM ent) GROUP BY ALL"
    o["bucket_range_join"] = "WITH b AS (SELECT i AS bucket, i * 50000 AS lo, (i + 1) * 50000 AS hi FROM range(10) r(i)) SELECT bucket, count(*) AS n FROM orders JOIN b ON o_totalprice >= lo AND o_totalprice < hi GROUP BY bucket"
    o["asof_prev_event"] = f"WITH {EVENTS} SELECT o_orderkey, qid AS event_id FROM orders ASOF JOIN (SELECT qid, ts, user_id FROM ev) e ON o_custkey = e.user_id AND o_orderdate + INTERVAL 25 YEAR >= e.ts"
    o["interval_concurrency"] = "SELECT a.event_id, count(*) - 1 AS near FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR GROUP BY a.event_id"
    o["view_sizes_cube"] = "SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag, l_linestatus) AS BIGINT) AS gid, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"
    o["scores_rollup"] = f"WITH {EVENTS} SELECT feature, CAST(ts AS DATE) AS day, CAST(sum(mult) AS BIGINT) AS n FROM tok JOIN ev USING (qid) GROUP BY ROLLUP (feature, day)"
    o["scores_gsets"] = "SELECT event_type, user_id, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id), ())"
    o["gamma_grid"] = on_sample("SELECT * FROM (" + " UNION ALL ".join(f"SELECT feature, round(sum(CASE WHEN ms > 0 THEN d * (ln(ms + {g!r}) - ln({g!r})) ELSE 0 END), 6) AS g, '{n}' AS col {_B} GROUP BY feature" for n, g in (("g1", 1.0), ("g2", 0.001), ("g3", 1e-10))) + ") PIVOT (max(g) FOR col IN ('g1', 'g2', 'g3') GROUP BY feature)")
    o["profile_numeric"] = f"WITH {ORDERS} SELECT feature, round(avg(v), 3) AS mean, round(median(v), 3) AS median, round(quantile_cont(v, 0.9), 3) AS p90 FROM numv GROUP BY feature"
    o["moving_freq"] = "WITH d AS (SELECT event_type, CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY ALL) SELECT event_type, day, CAST(sum(n) OVER (PARTITION BY event_type ORDER BY day RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS n7 FROM d"
    o["event_bigrams"] = f"WITH {EVENTS} SELECT token, count(*) AS n FROM tok WHERE feature = 'bigram' GROUP BY token"
    o["json_props"] = "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY k"
    o["hour_tokens"] = "SELECT CAST(hour(ts) AS INTEGER) AS hour, count(*) AS n FROM events GROUP BY ALL"
    o["tumbling_counts"] = "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL"
    o["sliding_counts"] = "SELECT CAST(d AS TIMESTAMP) AS start, count(*) AS n FROM (SELECT unnest(generate_series(date_trunc('day', ts) - INTERVAL 6 DAY, date_trunc('day', ts), INTERVAL 1 DAY)) AS d FROM events) GROUP BY d"
    o["session_counts"] = "WITH s AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 6 HOUR THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), g AS (SELECT user_id, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM s) SELECT user_id, count(DISTINCT k) AS sessions, count(*) AS n FROM g GROUP BY user_id"
    o["pred_mix"] = "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 300000 AND o_orderpriority LIKE '%-%' AND o_orderdate IS NOT NULL GROUP BY ALL"
    first, later = (f"SELECT feature, token FROM tok JOIN bt USING (qid) WHERE batch {which}" for which in ("= 1", "> 1"))
    for name, how in (("set_intersect", "INTERSECT"), ("set_except", "EXCEPT")):
        o[name] = f"WITH {_batch_tokens(7)} {first} {how} {later}"
        o[f"{name}_all"] = f"WITH {_batch_tokens(7)} SELECT feature, token, count(*) AS n FROM ({first} {how} ALL {later}) GROUP BY ALL"
    return o
