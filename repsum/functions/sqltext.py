"""SQL text: fingerprints, and the syntax features of queries.

Fingerprints are native expressions, so that only texts that differ in more than literals reach the parser. It
is a tokenizer with a stack of clauses: it knows sub-queries, common table expressions, comma
joins, aliases, quoted names, CASE, window functions and ordinals.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F, types as T

_TOKEN = re.compile(r"""\s+|--[^\n]*|/\*.*?\*/|'(?:[^']|'')*'|"(?:[^"]|"")*"|`[^`]*`|\d+(?:\.\d+)?(?:[eE][+-]?\d+)?|[A-Za-z_][\w$]*|<>|<=|>=|!=|\|\||.""", re.DOTALL)
#: Words that are followed by a parenthesis without being calls, or that end an alias.
_NOT_CALLS = frozenset("in exists and or not as on using values over filter within from where select by having any all some case when then else between like is union intersect except join left right full inner cross outer with partition order group limit distinct interval end".split())
_CLAUSES = frozenset("select from where group order having limit union intersect except window qualify".split())
#: Words that stand in expressions without naming a column.
_NO_COLUMN = frozenset("asc desc nulls first last null true false unknown grouping sets rows range preceding following unbounded current row current_date current_timestamp".split())
#: What a column can be compared by.
_COMPARISONS = frozenset("= <> != < <= > >= between in like ilike is".split())
_NO_ALIAS = _NOT_CALLS | _CLAUSES | {"natural", "lateral", "set", "offset", "fetch", "asc", "desc", "nulls", "first", "last"}


_STRING = r"'(?:[^']|'')*'"
_QUOTED = r'"(?:[^"]|"")*"|`[^`]*`'
_NUMBER = r"\d+(?:\.\d+)?(?:e[+-]?\d+)?"


def fingerprint(sql: Column) -> Column:
    """Lower case, no comments, literals as ?, IN lists of literals as one ?, single spaces.

    Numbers after BY or a comma stay, since they may be ordinals of GROUP BY and ORDER BY: texts
    that differ in an ordinal never share a fingerprint.
    """
    text = F.regexp_replace(sql, rf"({_STRING}|{_QUOTED})|--[^\n]*|/\*[\s\S]*?\*/", "$1 ")
    text = F.regexp_replace(F.lower(text), rf"({_QUOTED})|{_STRING}", "$1?")
    text = F.regexp_replace(text, "([\"`])\\?", "$1")
    text = F.regexp_replace(F.regexp_replace(text, r"\s+", " "), r" ?, ?", ", ")
    text = F.regexp_replace(text, rf"\bin \? ?\( ?(?:\?|{_NUMBER})(?:, (?:\?|{_NUMBER}))* ?\)|\bin ?\( ?(?:\?|{_NUMBER}) ?(?:, (?:\?|{_NUMBER}) ?)*\)", "in (?)")
    text = F.regexp_replace(text, rf"(?<!by |, )(?<![\w.\"`]){_NUMBER}\b", "?")
    return F.trim(text)


def mark(sql: Column) -> Column:
    """What texts must share to have the same tokens: the fingerprint, and quoted names as they are written."""
    return F.md5(F.concat_ws("|", fingerprint(sql), F.array_join(F.regexp_extract_all(sql, F.lit(f"({_QUOTED})"), F.lit(1)), "|")))


def _lex(sql: str, fold: bool = False) -> list[str]:
    """Tokens without white space and comments; ``fold`` lowers names that are not quoted."""
    out = []
    for m in _TOKEN.finditer(sql):
        t = m.group()
        if t.isspace() or t.startswith("--") or t.startswith("/*"):
            continue
        out.append(t[1:-1] if t[0] in '"`' else t.lower() if fold and t[0] != "'" else t)
    return out


def _name(tokens: list[str], i: int) -> tuple[str, int]:
    """A possibly dotted name that starts at i, and the position after it."""
    parts = [tokens[i]]
    i += 1
    while i + 1 < len(tokens) and tokens[i] == "." and re.match(r"[\w$]", tokens[i + 1]):
        parts.append(tokens[i + 1])
        i += 2
    return ".".join(parts), i


def _is_name(t: str) -> bool:
    return bool(re.match(r"[A-Za-z_]", t)) and t.lower() not in _NO_ALIAS


def _is_value(t: str) -> bool:
    """Whether a token ends an operand: a name, a number or a string."""
    return t.startswith("'") or t[:1].isdigit() or _is_name(t)


class _Scope:
    def __init__(self) -> None:
        self.clause = ""
        self.tables: list[tuple[str, str]] = []  # table, alias
        self.items: list[list[str]] = []  # the columns of each selected item, by position
        self.aliases: dict[str, int] = {}  # names given to items
        self.group: list[str] = []
        self.order: list[str] = []
        self.where: list[str] = []
        self.tests: list[tuple[str, str]] = []  # a column and what it is compared by
        self.calls: list[str] = []
        self.joins = 0


def parse(sql: str, fold: bool = False, predicates: bool = False) -> list[tuple[str, str]]:
    """(feature, token) pairs: function_call, table_reference, group_by, order_by, where_column; and one n_joins.

    Calls are those of SELECT clauses (and of CALL); GROUP BY and ORDER BY give the columns of their
    expressions, and ordinals and aliases those of the selected item that they stand for.
    ``predicates`` adds a feature predicate: columns of WHERE with what they are compared by.
    """
    tokens = _lex(sql, fold)
    ctes = {tokens[i - 1].lower() for i in range(1, len(tokens) - 1) if tokens[i].lower() == "as" and tokens[i + 1] == "(" and _is_name(tokens[i - 1]) and (i < 2 or tokens[i - 2].lower() in ("with", ",", "recursive"))} if tokens and tokens[0].lower() == "with" else set()
    done: list[_Scope] = []
    _scan(tokens, 0, done, _Scope())
    out: list[tuple[str, str]] = []
    joins = 0
    for s in done:
        real = [t for t, _ in s.tables if t.lower() not in ctes]
        names = {a.lower(): t for t, a in s.tables}
        only = s.tables[0][0] if len(s.tables) == 1 else None

        def full(c: str, names=names, only=only) -> str:
            head, _, tail = c.partition(".")
            if tail and head.lower() in names:
                return f"{names[head.lower()]}.{tail}"
            return f"{only}.{c}" if only and not tail and re.match(r"[A-Za-z_]", c) else c

        def stands_for(c: str, s=s) -> list[str]:
            if c.isdigit():
                return s.items[int(c) - 1] if 0 < int(c) <= len(s.items) else []
            return s.items[s.aliases[c.lower()]] if c.lower() in s.aliases else [c]

        out += [("function_call", c.upper()) for c in s.calls] + [("table_reference", t) for t in real]
        for kind, listed in (("group_by", s.group), ("order_by", s.order)):
            out += [(kind, full(c)) for entry in listed for c in stands_for(entry)]
        out += [("where_column", full(c)) for c in s.where]
        out += [("predicate", f"{full(c)} {by}") for c, by in s.tests if predicates]
        joins += s.joins
    return [*out, ("n_joins", str(joins))]


def _is_column(tokens: list[str], i: int, after: int, depth: int) -> bool:
    """Whether the name from i up to ``after`` is a column and not a part of a typed literal, a cast or extract()."""
    before = tokens[i - 1] if i else ""
    behind = tokens[after] if after < len(tokens) else ""
    if behind.startswith("'") or before.startswith("'") or re.match(r"\d", before):  # date '...', interval '1' day
        return False
    if depth and (behind.lower() == "from" or before.lower() == "as"):  # extract(year from d), cast(x as int)
        return False
    return tokens[i].lower() not in _NO_COLUMN


def _scan(tokens: list[str], i: int, done: list[_Scope], scope: _Scope, in_window: bool = False) -> int:
    """Read one query level up to its closing parenthesis; scopes of inner queries are added to ``done``."""
    depth, start = 0, len(done)
    while i < len(tokens):
        t, low = tokens[i], tokens[i].lower()
        following = tokens[i + 1] if i + 1 < len(tokens) else ""
        if t == "(":
            if following.lower() in ("select", "with"):
                i = _scan(tokens, i + 1, done, _Scope())
                if scope.clause == "from" and i < len(tokens):  # an alias of the sub-query
                    if tokens[i].lower() == "as":
                        i += 1
                    if i < len(tokens) and _is_name(tokens[i]):
                        i += 1
                continue
            depth += 1
        elif t == ")":
            if depth == 0:
                done.insert(start, scope)
                return i + 1
            depth -= 1
        elif low == "over" and following == "(":
            level, i = 1, i + 2
            while i < len(tokens) and level:
                level += (tokens[i] == "(") - (tokens[i] == ")")
                i += 1
            continue
        elif low in ("union", "intersect", "except") and depth == 0:
            done.insert(start, scope)
            scope = _Scope()
        elif low in _CLAUSES and depth == 0 and not (low in ("group", "order") and following.lower() != "by"):
            scope.clause = low
            if low == "select":
                scope.items.append([])
            if low in ("group", "order"):
                i += 1
        elif low == "join":
            scope.joins += 1
            scope.clause = "from"
        elif low in ("on", "using") and scope.clause == "from":
            scope.clause = "on"
        elif t == "," and scope.clause in ("from", "on") and depth == 0:
            scope.joins += 1
            scope.clause = "from"
        elif t == "," and scope.clause == "select" and depth == 0:
            scope.items.append([])
        elif re.match(r"[A-Za-z_]", t) and low not in _NOT_CALLS | _CLAUSES:
            name, after = _name(tokens, i)
            called = after < len(tokens) and tokens[after] == "("
            if scope.clause == "from" and not called and depth == 0:
                alias, i = name.split(".")[-1], after
                if i < len(tokens) and tokens[i].lower() == "as":
                    i += 1
                if i < len(tokens) and _is_name(tokens[i]):
                    alias = tokens[i]
                    i += 1
                scope.tables.append((name, alias))
                continue
            if called and scope.clause in ("select", ""):
                scope.calls.append(name)
            elif scope.clause == "select" and not called and scope.items:
                before = tokens[i - 1].lower() if i else ""
                ends = after >= len(tokens) or tokens[after] in (",", ")") or tokens[after].lower() == "from"
                # a name that follows AS, or a finished expression, names the item
                if depth == 0 and ends and (before == "as" or before in (")", "end") or _is_value(tokens[i - 1])):
                    scope.aliases[name.lower()] = len(scope.items) - 1
                elif low != "distinct" and _is_column(tokens, i, after, depth):
                    scope.items[-1].append(name)
            elif scope.clause in ("group", "order") and not called and _is_column(tokens, i, after, depth):
                getattr(scope, scope.clause).append(name)
            elif scope.clause == "where" and not called and _is_column(tokens, i, after, depth):
                scope.where.append(name)
                by = [x.lower() for x in tokens[after : after + 2] if x.lower() != "not"][:1]
                if by and by[0] in _COMPARISONS and not (after + 1 < len(tokens) and by[0] in ("=", "<", ">", "<=", ">=") and _is_name(tokens[after + 1]) and not (after + 2 < len(tokens) and tokens[after + 2].startswith("'"))):
                    scope.tests.append((name, by[0]))
            i = after
            continue
        elif t.isdigit() and scope.clause in ("group", "order") and depth == 0 and tokens[i - 1].lower() in ("by", ","):
            getattr(scope, scope.clause).append(t)
        i += 1
    done.insert(start, scope)
    return i


_PAIRS = T.ArrayType(T.StructType([T.StructField("feature", T.StringType()), T.StructField("token", T.StringType())]))


@F.pandas_udf(_PAIRS)
def _parse_udf(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for s in texts:
        yield s.map(lambda t: [{"feature": a, "token": b} for a, b in parse(t, True, True)] if t else [])


def sql_tokens(log: DataFrame, kinds: tuple[str, ...] = ("function_call", "table_reference", "group_by", "order_by")) -> DataFrame:
    """(qid, feature, token, mult): distinct texts up to literals are parsed once and joined back.

    Names that are not quoted are lowered, so entries that share a mark have the same tokens
    whichever of them is parsed.
    """
    marked = log.select("qid", "sql", mark(F.col("sql")).alias("mark"))
    texts = marked.groupBy("mark").agg(F.min("sql").alias("sql"))
    parsed = texts.select("mark", F.explode(_parse_udf("sql")).alias("t")).select("mark", "t.feature", "t.token").where(F.col("feature").isin(*kinds))
    counted = parsed.groupBy("mark", "feature", "token").agg(F.count("*").alias("mult"))
    return marked.select("qid", "mark").join(counted, "mark").select("qid", "feature", "token", "mult")


def shapes_of(log: DataFrame) -> DataFrame:
    """(mark, n, qid, tables, tests, grouped): texts up to literals, how often each stands in the log, and the
    tables, predicates (column and comparison) and grouping columns of each, sorted, without repeats."""
    texts = log.select("qid", "sql", mark(F.col("sql")).alias("mark")).groupBy("mark").agg(F.count("*").alias("n"), F.min("qid").alias("qid"), F.min("sql").alias("sql"))
    parsed = texts.select("mark", "n", "qid", _parse_udf("sql").alias("t"))
    of = lambda kind: F.array_sort(F.array_distinct(F.transform(F.filter("t", lambda x: x["feature"] == kind), lambda x: x["token"])))
    return parsed.select("mark", "n", "qid", of("table_reference").alias("tables"), of("predicate").alias("tests"), of("group_by").alias("grouped"))


def join_counts(log: DataFrame) -> DataFrame:
    """(qid, n_joins)."""
    return sql_tokens(log, ("n_joins",)).select("qid", F.col("token").cast("long").alias("n_joins"))


def scrub(sql: str | None, salt: str) -> str | None:
    """A text without comments whose strings and numbers are salted digests of themselves, equal ones alike.

    A number keeps its count of digits. Ordinals and the counts of LIMIT, OFFSET and FETCH stay.
    """
    if sql is None:
        return None
    out, clause, depth, before = [], {}, 0, ""
    for m in _TOKEN.finditer(sql):
        t, low = m.group(), m.group().lower()
        if t.startswith("--") or t.startswith("/*"):
            out.append(" ")
            continue
        if not t.isspace():
            if t[0] == "'":
                t = f"'{hashlib.sha256((salt + t).encode()).hexdigest()[:12]}'"
            elif t[0].isdigit():
                ordinal = clause.get(depth) == "by" and before in ("by", ",")
                if not ordinal and before not in ("limit", "offset", "fetch", "first", "next"):
                    whole, dot, part = t.partition(".")
                    t = _digits(salt, t, len(whole)) + (dot + _digits(salt, f"{t}.", len(part)) if dot else "")
            elif low in ("select", "from", "where", "having", "limit", "by", "on", "set", "values"):
                clause[depth] = low
            depth += (t == "(") - (t == ")")
            clause |= {depth: ""} if t == "(" else {}
            before = low
        out.append(t)
    return "".join(out)


def _digits(salt: str, text: str, n: int) -> str:
    """n digits, the first not zero, from a digest."""
    raw = str(int(hashlib.sha256(f"{salt}#{text}".encode()).hexdigest(), 16))
    return (str(int(raw[0]) % 9 + 1) + (raw[1:] * (1 + n // 60))[: n - 1]) if n else ""


@F.pandas_udf(T.StringType())
def _scrub_udf(texts: pd.Series, salts: pd.Series) -> pd.Series:
    return pd.Series([scrub(t, s) for t, s in zip(texts, salts)], dtype=object)


def anonymise(sql: Column, salt: str) -> Column:
    """Strings and numbers replaced by salted digests, see scrub()."""
    return _scrub_udf(sql, F.lit(salt))


def register(spark) -> None:
    """SQL surface: token_bag(sql) and token_bucket(value, low, high, buckets) as functions, tokens_of(sql) as a table function."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="feature string, token string")
    class TokensOf:
        def eval(self, sql: str):
            yield from parse(sql or "")

    spark.udf.register("token_bag", _parse_udf)
    spark.udtf.register("tokens_of", TokensOf)
    spark.sql(
        """CREATE OR REPLACE TEMPORARY FUNCTION token_bucket(value BIGINT, low BIGINT, high BIGINT, buckets BIGINT) RETURNS BIGINT
        RETURN CASE WHEN value IS NULL THEN NULL WHEN high = low THEN 0 ELSE ((least(greatest(value, low), high) - low) * buckets) DIV (high - low) END"""
    )
