"""Logs of SQL text over the given tables, rendered from described templates.

A template lists what a query of it has; the text is rendered from the description, so the
tokens that a parser must find are known. Literals are drawn for each instance; what they keep of
a table decides the modelled statistics of the entry.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, functions as F

from repsum.sources.tables import read

#: How tables join to each other.
JOINS = {
    ("lineitem", "orders"): "lineitem.l_orderkey = orders.o_orderkey",
    ("lineitem", "part"): "lineitem.l_partkey = part.p_partkey",
    ("lineitem", "supplier"): "lineitem.l_suppkey = supplier.s_suppkey",
    ("orders", "customer"): "orders.o_custkey = customer.c_custkey",
    ("customer", "nation"): "customer.c_nationkey = nation.n_nationkey",
    ("supplier", "nation"): "supplier.s_nationkey = nation.n_nationkey",
    ("nation", "region"): "nation.n_regionkey = region.r_regionkey",
}
#: Predicates by column, with a literal's slot.
PREDICATES = {
    "lineitem.l_returnflag": "= '{f}'",
    "lineitem.l_linestatus": "= '{s}'",
    "lineitem.l_quantity": "< {q}",
    "lineitem.l_discount": "between 0.0{d} and 0.0{e}",
    "lineitem.l_shipdate": ">= date '{y}-01-01'",
    "orders.o_orderstatus": "= '{o}'",
    "orders.o_orderpriority": "= '{p}'",
    "orders.o_orderdate": "< date '{y}-06-01'",
    "customer.c_mktsegment": "= '{m}'",
    "part.p_brand": "= 'Brand#{b}'",
    "part.p_type": "= '{t}'",
    "part.p_size": "= {z}",
    "nation.n_name": "= 'NATION{n}'",
    "region.r_name": "= '{r}'",
    "supplier.s_acctbal": "> {a}",
}
#: The literals that stand in the slots.
_WORDS = {
    "f": "ANR", "s": "FO", "o": "FOP", "p": ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"),
    "m": ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"), "t": ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"),
    "r": ("AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST"),
}


@dataclass(frozen=True)
class Template:
    name: str
    tables: tuple[str, ...]
    calls: tuple[tuple[str, str], ...]
    where: tuple[str, ...] = ()
    group: tuple[str, ...] = ()
    order: tuple[str, ...] = ()


def _t(name: str, tables: str, calls: str, where: str = "", group: str = "", order: str = "") -> Template:
    split = lambda s: tuple(s.split())
    return Template(name, split(tables), tuple(tuple(c.split(":")) for c in calls.split()), split(where), split(group), split(order))


#: Twenty-two report queries over the whole schema.
REPORTS = (
    _t("h01", "lineitem", "SUM:lineitem.l_quantity SUM:lineitem.l_extendedprice AVG:lineitem.l_discount COUNT:*", "lineitem.l_shipdate", "lineitem.l_returnflag lineitem.l_linestatus", "lineitem.l_returnflag lineitem.l_linestatus"),
    _t("h02", "part lineitem supplier nation region", "MIN:supplier.s_acctbal", "part.p_size region.r_name", "", "nation.n_name"),
    _t("h03", "customer orders lineitem", "SUM:lineitem.l_extendedprice", "customer.c_mktsegment orders.o_orderdate", "orders.o_orderdate", "orders.o_orderdate"),
    _t("h04", "orders", "COUNT:*", "orders.o_orderdate", "orders.o_orderpriority", "orders.o_orderpriority"),
    _t("h05", "customer orders lineitem nation region", "SUM:lineitem.l_extendedprice", "region.r_name orders.o_orderdate", "nation.n_name", ""),
    _t("h06", "lineitem", "SUM:lineitem.l_extendedprice", "lineitem.l_shipdate lineitem.l_discount lineitem.l_quantity"),
    _t("h07", "supplier lineitem nation", "SUM:lineitem.l_extendedprice", "nation.n_name lineitem.l_shipdate", "nation.n_name", "nation.n_name"),
    _t("h08", "part lineitem orders", "AVG:lineitem.l_discount", "part.p_type orders.o_orderdate", "orders.o_orderstatus", "orders.o_orderstatus"),
    _t("h09", "part lineitem supplier nation", "SUM:lineitem.l_extendedprice", "part.p_brand", "nation.n_name", "nation.n_name"),
    _t("h10", "customer orders lineitem nation", "SUM:lineitem.l_extendedprice", "lineitem.l_returnflag", "nation.n_name", ""),
    _t("h11", "supplier nation", "SUM:supplier.s_acctbal COUNT:*", "nation.n_name", "supplier.s_nationkey", "supplier.s_nationkey"),
    _t("h12", "orders lineitem", "COUNT:*", "lineitem.l_shipdate lineitem.l_linestatus", "orders.o_orderpriority", "orders.o_orderpriority"),
    _t("h13", "customer orders", "COUNT:orders.o_orderkey", "orders.o_orderpriority", "customer.c_mktsegment", "customer.c_mktsegment"),
    _t("h14", "lineitem part", "SUM:lineitem.l_extendedprice AVG:lineitem.l_tax", "lineitem.l_shipdate"),
    _t("h15", "lineitem supplier", "MAX:lineitem.l_extendedprice", "lineitem.l_shipdate", "supplier.s_name", "supplier.s_name"),
    _t("h16", "part supplier lineitem", "COUNT:supplier.s_suppkey", "part.p_brand part.p_size", "part.p_brand part.p_type", "part.p_brand"),
    _t("h17", "lineitem part", "AVG:lineitem.l_quantity", "part.p_brand part.p_type"),
    _t("h18", "customer orders lineitem", "SUM:lineitem.l_quantity", "lineitem.l_quantity", "customer.c_name", "orders.o_totalprice"),
    _t("h19", "lineitem part", "SUM:lineitem.l_extendedprice", "part.p_brand lineitem.l_quantity part.p_size"),
    _t("h20", "supplier nation lineitem part", "COUNT:*", "nation.n_name part.p_type", "", "supplier.s_name"),
    _t("h21", "supplier lineitem orders nation", "COUNT:*", "orders.o_orderstatus nation.n_name", "supplier.s_name", "supplier.s_name"),
    _t("h22", "customer", "COUNT:* SUM:customer.c_acctbal", "customer.c_mktsegment", "customer.c_nationkey", "customer.c_nationkey"),
)
#: Thirteen star queries in four flights; each has exactly one SUM, and flights 2 to 4 group and order.
STARS = (
    _t("s11", "lineitem orders", "SUM:lineitem.l_extendedprice", "orders.o_orderdate lineitem.l_discount lineitem.l_quantity"),
    _t("s12", "lineitem orders", "SUM:lineitem.l_extendedprice", "orders.o_orderstatus lineitem.l_discount lineitem.l_quantity"),
    _t("s13", "lineitem orders", "SUM:lineitem.l_extendedprice", "lineitem.l_shipdate lineitem.l_discount lineitem.l_quantity"),
    _t("s21", "lineitem orders part supplier", "SUM:lineitem.l_extendedprice", "part.p_type", "orders.o_orderstatus part.p_brand", "orders.o_orderstatus part.p_brand"),
    _t("s22", "lineitem orders part supplier", "SUM:lineitem.l_extendedprice", "part.p_brand", "orders.o_orderstatus part.p_brand", "orders.o_orderstatus part.p_brand"),
    _t("s23", "lineitem orders part supplier", "SUM:lineitem.l_extendedprice", "part.p_brand part.p_type", "orders.o_orderstatus part.p_brand", "orders.o_orderstatus part.p_brand"),
    _t("s31", "lineitem orders customer supplier", "SUM:lineitem.l_quantity", "customer.c_mktsegment orders.o_orderdate", "customer.c_nationkey supplier.s_nationkey orders.o_orderstatus", "orders.o_orderstatus"),
    _t("s32", "lineitem orders customer supplier", "SUM:lineitem.l_quantity", "customer.c_mktsegment orders.o_orderpriority", "customer.c_nationkey supplier.s_nationkey orders.o_orderstatus", "orders.o_orderstatus"),
    _t("s33", "lineitem orders customer supplier", "SUM:lineitem.l_quantity", "customer.c_mktsegment orders.o_orderstatus", "customer.c_nationkey supplier.s_nationkey", "customer.c_nationkey"),
    _t("s34", "lineitem orders customer supplier", "SUM:lineitem.l_quantity", "orders.o_orderstatus orders.o_orderpriority", "customer.c_nationkey supplier.s_nationkey", "supplier.s_nationkey"),
    _t("s41", "lineitem orders customer supplier part", "SUM:lineitem.l_extendedprice", "customer.c_mktsegment part.p_type", "orders.o_orderstatus customer.c_nationkey", "orders.o_orderstatus customer.c_nationkey"),
    _t("s42", "lineitem orders customer supplier part", "SUM:lineitem.l_extendedprice", "customer.c_mktsegment part.p_type orders.o_orderdate", "orders.o_orderstatus supplier.s_nationkey part.p_type", "orders.o_orderstatus supplier.s_nationkey part.p_type"),
    _t("s43", "lineitem orders customer supplier part", "SUM:lineitem.l_extendedprice", "part.p_brand orders.o_orderdate", "orders.o_orderstatus supplier.s_nationkey part.p_brand", "orders.o_orderstatus supplier.s_nationkey part.p_brand"),
)


def draw(*key: object) -> int:
    """A fixed pseudo-random number below 2**32 for a key."""
    return int(hashlib.md5("|".join(map(str, key)).encode()).hexdigest()[:8], 16)


def literals(name: str, i: int) -> dict[str, object]:
    """The literals of the i-th instance of a template, drawn independently of each other."""
    n = lambda slot, size: draw(name, i, slot) % size
    out: dict[str, object] = {k: v[n(k, len(v))] for k, v in _WORDS.items()}
    d = 1 + n("d", 4)
    return out | {"q": 5 + n("q", 45), "d": d, "e": d + 1 + n("e", 9 - d), "y": 1995 + n("y", 6), "b": 1 + n("b", 25), "z": 1 + n("z", 50), "n": n("n", 25), "a": 100 * n("a", 90)}


def kept(column: str, given: dict[str, object]) -> int:
    """Rows in thousandths that the predicate on a column keeps with these literals."""
    if column in ("lineitem.l_quantity", "lineitem.l_discount", "lineitem.l_shipdate", "orders.o_orderdate", "supplier.s_acctbal"):
        share = {"lineitem.l_quantity": (given["q"] - 1) / 50, "lineitem.l_discount": (given["e"] - given["d"] + 1) / 11, "lineitem.l_shipdate": (2002 - given["y"]) / 7, "orders.o_orderdate": (given["y"] - 1994.6) / 6.6, "supplier.s_acctbal": 1 - (given["a"] + 999) / 10_999}
        return max(1, round(1000 * share[column]))
    slot = PREDICATES[column].split("{")[1][0]
    # equal values are not equally frequent: the first of m words is met with twice the weight of the last
    size = len(_WORDS[slot]) if slot in _WORDS else {"b": 25, "z": 50, "n": 25}[slot]
    at = _WORDS[slot].index(given[slot]) if slot in _WORDS else int(given[slot]) % size
    return max(1, round(1000 * (2 - at / max(1, size - 1)) / (1.5 * size)))


def render(t: Template, i: int) -> str:
    given = literals(t.name, i)
    calls = [f"{f.lower()}({c})" for f, c in t.calls]
    on = [JOINS.get((a, b)) or JOINS.get((b, a)) for k, a in enumerate(t.tables) for b in t.tables[k + 1 :]]
    tests = [x for x in on if x] + [f"{c} {PREDICATES[c].format(**given)}" for c in t.where]
    parts = [f"select {', '.join([*t.group, *calls])}", f"from {', '.join(t.tables)}"]
    if tests:
        parts.append(f"where {' and '.join(tests)}")
    if t.group:
        parts.append(f"group by {', '.join(t.group)}")
    if t.order:
        parts.append(f"order by {', '.join(t.order)}")
    return " ".join(parts)


def expected_tokens(t: Template) -> list[tuple[str, str]]:
    """What the four categorical features of any instance hold, repeats included."""
    return [("function_call", f) for f, _ in t.calls] + [("table_reference", x) for x in t.tables] + [("group_by", c) for c in t.group] + [("order_by", c) for c in t.order]


#: Rows of each table at the unit scale of the modelled statistics.
UNIT_ROWS = {"lineitem": 6_000_000, "orders": 1_500_000, "part": 200_000, "customer": 150_000, "supplier": 10_000, "nation": 25, "region": 5}


#: Numeric features of the SQL logs.
STATISTICS = ["exec_ms", "plan_ms", "rows_read", "rows_out", "cpu_ms", "n_joins"]


def statistics(t: Template, i: int) -> tuple[int, ...]:
    """The statistics of an instance, modelled: input rows after predicates per table, joined rows, and times.

    Times follow the rows that are scanned, joined and sorted, with a load of up to a fifth more.
    """
    given = literals(t.name, i)
    share = {x: 1000 for x in t.tables}
    for c in t.where:
        own = c.split(".")[0]
        share[own] = max(1, share[own] * kept(c, given) // 1000)
    rows_read = sum(UNIT_ROWS[x] for x in t.tables)
    rows = max(UNIT_ROWS[x] for x in t.tables)
    for x in t.tables:
        rows = max(1, rows * share[x] // 1000)
    groups = 1
    for c in t.group:
        groups = min(rows, groups * (5 + draw(c) % 200))
    rows_out = groups if t.group else 1 if t.calls else rows
    load = 1000 + draw(t.name, i, "load") % 200
    work = rows_read // 2000 + (len(t.tables) - 1) * rows // 500 + (rows // 800 if t.group else 0) + rows_out // 100
    plan_ms = 2 + 3 * (len(t.tables) - 1) ** 2 + len(t.where) + draw(t.name, i, "plan") % 4
    exec_ms = max(1, work * load // 1000)
    return exec_ms, plan_ms, rows_read, rows_out, exec_ms * (70 + draw(t.name, i, "cpu") % 25) // 100, len(t.tables) - 1


_SQL_LOG = "qid long, template string, sql string, exec_ms long, plan_ms long, rows_read long, rows_out long, cpu_ms long, n_joins long"


def sql_log(spark: SparkSession, templates: tuple[Template, ...], instances: int = 100) -> DataFrame:
    """(qid, template, sql, statistics): ``instances`` of each template in turn."""
    rows = [(n * instances + i, t.name, render(t, i), *statistics(t, i)) for n, t in enumerate(templates) for i in range(instances)]
    return spark.createDataFrame(rows, _SQL_LOG)


#: Instances of a template, and literals of an odd text, in a log over the orders table.
ORDER_INSTANCES, ODD_INSTANCES = 100, 20


def _per_order(spark: SparkSession, sf_dir: str, kinds: int, instances: int) -> DataFrame:
    """(qid, k, i): an order is a query of the log; its key deals the text, its customer the literals."""
    orders = read(spark, sf_dir, "orders").where("o_orderkey is not null")
    at = lambda c, n: F.pmod(F.coalesce(c, F.lit(0)), F.lit(n)).cast("int")
    return orders.select(F.col("o_orderkey").alias("qid"), at("o_orderkey", kinds).alias("k"), at("o_custkey", instances).alias("i"))


def order_log(spark: SparkSession, sf_dir: str, templates: tuple[Template, ...], instances: int = ORDER_INSTANCES) -> DataFrame:
    """The columns of sql_log() with an entry for each order; texts are a bounded table that is broadcast."""
    rows = [(k, i, t.name, render(t, i), *statistics(t, i)) for k, t in enumerate(templates) for i in range(instances)]
    texts = spark.createDataFrame(rows, "k int, i int, " + _SQL_LOG.split(", ", 1)[1])
    return _per_order(spark, sf_dir, len(templates), instances).join(F.broadcast(texts), ["k", "i"]).drop("k", "i")


def odd_order_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(qid, sql): the odd texts with an entry for each order."""
    rows = [(k, i, sql.format(1990 + i)) for k, (sql, _) in enumerate(ODD_TEXTS) for i in range(ODD_INSTANCES)]
    texts = spark.createDataFrame(rows, "k int, i int, sql string")
    return _per_order(spark, sf_dir, len(ODD_TEXTS), ODD_INSTANCES).join(F.broadcast(texts), ["k", "i"]).select("qid", "sql")


#: Different instances of a template in a mixed log; a longer log repeats them under a load of its own.
INSTANCES = 400


def mixed_log(spark: SparkSession, n: int) -> DataFrame:
    """The same columns at any length: both sets of templates, dealt by qid; times vary with the entry."""
    every = REPORTS + STARS
    texts = spark.createDataFrame([(k, i, t.name, render(t, i), *statistics(t, i)) for k, t in enumerate(every) for i in range(INSTANCES)], "k int, i int, " + _SQL_LOG.split(", ", 1)[1])
    ids = spark.range(n).select(F.col("id").alias("qid"), F.pmod("id", F.lit(len(every))).cast("int").alias("k"), F.pmod(F.expr(f"id div {len(every)}"), F.lit(INSTANCES)).cast("int").alias("i"))
    load = F.lit(1000) + F.pmod(F.xxhash64("qid"), F.lit(300))
    times = {c: F.greatest(F.lit(1), F.floor(F.col(c) * load / 1000)).cast("long") for c in ("exec_ms", "cpu_ms")}
    return ids.join(F.broadcast(texts), ["k", "i"]).drop("k", "i").withColumns(times)


#: Texts with what must be found in them; {} takes a literal. Ordinals, aliases, expressions, quoted
#: names, case, comments and lists of literals.
ODD_TEXTS: tuple[tuple[str, str], ...] = (
    ("select a, sum(b) from t where c = {} group by 1 order by 1", "f:SUM t:t g:t.a o:t.a"),
    ("select a, sum(b) from t where c = {} group by 1 order by 2", "f:SUM t:t g:t.a o:t.b"),
    ("SELECT A, SUM(B) FROM T WHERE C = {} GROUP BY 1 ORDER BY 2, 1", "f:SUM t:t g:t.a o:t.b o:t.a"),
    ("select extract(year from d) y, count(*) from t where x in (1, 2, {}) group by extract(year from d) order by y", "f:EXTRACT f:COUNT t:t g:t.d o:t.d"),
    ("select k, max(v) as top from u /* {} */ group by k order by max(v) desc, top", "f:MAX t:u g:u.k o:u.v o:u.v"),
    ('select "K" from "U" where "K" = {} order by 1', "t:U o:U.K"),
    ('select "k" from "U" where "k" = {} order by 1', "t:U o:U.k"),
    ("select p.a, q.b from p join q on p.k = q.k where p.z > {} order by 2, 1 -- 7", "t:p t:q o:q.b o:p.a"),
    ("select cast(a as int), b from t where date '{}-01-01' < d group by cast(a as int), b", "t:t g:t.a g:t.b f:CAST"),
    ("call refresh_all({}, 'x')", "f:REFRESH_ALL"),
)
_KINDS = {"f": "function_call", "t": "table_reference", "g": "group_by", "o": "order_by"}


def odd_tokens(text: str) -> list[tuple[str, str]]:
    return [(_KINDS[x[0]], x[2:]) for x in text.split()]


def odd_log(spark: SparkSession, instances: int = 20) -> DataFrame:
    """(qid, sql): the odd texts with other literals each time."""
    return spark.createDataFrame([(n * instances + i, sql.format(1990 + i)) for n, (sql, _) in enumerate(ODD_TEXTS) for i in range(instances)], "qid long, sql string")
