"""A deterministic what-if advisor: which indexes and views a workload would profit from.

It works on the text of the log: entries whose texts differ in literals only are one shape, with
the tables, compared columns and grouping columns that the parser finds. An index on (table,
column) lets a query that compares the column read only the rows that the predicate keeps; how
many it keeps is estimated from the column's distinct values, as optimisers do. A view holds the
groups of a set of tables by some columns; a query can read it instead of its tables if the
tables are the same, and the columns that it groups by or compares are among the view's. Costs
are rows read; they are modelled, not timed, so an advisor's patience is a budget of what-if
evaluations and not of minutes. Looking at one entry of a log under one candidate is one
evaluation: equal entries are costed once but charged each, since an advisor that is given a raw
log looks at every entry of it.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, functions as F

from repsum.functions.sqltext import mark, shapes_of

#: Rows in thousandths that a comparison keeps where distinct values do not tell.
RANGE_KEEPS = {"between": 250, "<": 333, ">": 333, "<=": 333, ">=": 333, "like": 100, "ilike": 100, "is": 50, "<>": 900, "!=": 900}
#: Shapes that the advisor's loop takes; a longer list of different texts needs a summary first.
MAX_SHAPES = 100_000


@dataclass(frozen=True)
class Structure:
    kind: str  # index or view
    tables: tuple[str, ...]
    cols: tuple[str, ...]
    rows: int = 0


@dataclass(frozen=True)
class Shape:
    """What the texts of one fingerprint share."""

    tables: tuple[str, ...]
    tests: tuple[tuple[str, str], ...] = ()  # compared column, comparison
    group: tuple[str, ...] = ()

    def needed(self) -> set[str]:
        return {*self.group, *(c for c, _ in self.tests)}


@dataclass
class Workload:
    """Shapes with how often each stands in the log; what all costs are sums over."""

    shapes: dict[str, Shape]
    counts: dict[str, int]
    table_rows: dict[str, int]
    distinct: dict[str, int] = field(default_factory=dict)  # of compared and grouping columns

    def keep(self, column: str, by: str) -> int:
        """Rows in thousandths that a comparison of a column keeps."""
        if by in RANGE_KEEPS:
            return RANGE_KEEPS[by]
        return min(1000, max(1, (3000 if by == "in" else 1000) // max(1, self.distinct.get(column, 1))))


def shape_table(log: DataFrame, known: list[str]) -> DataFrame:
    """(mark, n, tables, tests, grouped) of each shape of a log with its texts in ``sql``; names of ``known`` tables only."""
    own = F.array(*map(F.lit, known))
    of_table = lambda c: F.array_contains(own, F.substring_index(c, ".", 1))
    found = shapes_of(log).withColumn("tables", F.array_intersect("tables", own))
    return found.select("mark", "n", "tables", F.filter("tests", lambda t: of_table(t)).alias("tests"), F.filter("grouped", of_table).alias("grouped"))


def workload(spark: SparkSession, log: DataFrame, tables: dict[str, DataFrame]) -> Workload:
    """A log's shapes, and the sizes of what they read: one count per table and column of ``tables`` that they name."""
    rows = shape_table(log, sorted(tables)).limit(MAX_SHAPES + 1).collect()
    if len(rows) > MAX_SHAPES:
        raise ValueError(f"more than {MAX_SHAPES} different texts; advise on a summary of the log")
    shapes = {r["mark"]: Shape(tuple(r["tables"]), tuple(tuple(t.rsplit(" ", 1)) for t in r["tests"]), tuple(r["grouped"])) for r in rows}
    columns: dict[str, set[str]] = {t: set() for s in shapes.values() for t in s.tables}
    for s in shapes.values():
        for c in s.needed():
            columns.setdefault(c.split(".")[0], set()).add(c)
    sizes, distinct = {}, {}
    for t, cols in sorted(columns.items()):
        some = sorted(c for c in cols if c.split(".", 1)[1] in tables[t].columns)
        got = tables[t].agg(F.count("*").alias("n"), *(F.count_distinct(c.split(".", 1)[1]).alias(f"d{i}") for i, c in enumerate(some))).head()
        sizes[t] = got["n"]
        distinct |= {c: got[f"d{i}"] for i, c in enumerate(some)}
    return Workload(shapes, {r["mark"]: r["n"] for r in rows}, sizes, distinct)


def mark_of(log: DataFrame) -> DataFrame:
    """(qid, mark): the shape of each entry."""
    return log.select("qid", mark(F.col("sql")).alias("mark"))


def candidates(w: Workload, kinds: set[str]) -> list[Structure]:
    """Structures that some query of the workload could use, in a fixed order."""
    found: dict[Structure, None] = {}
    for name in sorted(w.counts):
        s = w.shapes[name]
        if "index" in kinds:
            for c, _ in s.tests:
                found[Structure("index", (c.split(".")[0],), (c,))] = None
        if "view" in kinds and s.group:
            cols = tuple(sorted(s.needed()))
            found[Structure("view", tuple(sorted(s.tables)), cols, view_rows(w, s.tables, cols))] = None
    return sorted(found, key=lambda x: (x.kind, x.tables, x.cols))


def view_rows(w: Workload, tables: tuple[str, ...], cols: tuple[str, ...]) -> int:
    """Groups of a view: combinations of its columns' values, at most the rows of its largest table."""
    groups = 1
    for c in cols:
        groups *= max(1, w.distinct.get(c, 1))
    return min(groups, max(w.table_rows[x] for x in tables))


def query_cost(w: Workload, s: Shape, design: list[Structure]) -> int:
    """Rows that a query of the shape reads under a design."""
    total = 0
    for tbl in s.tables:
        rows = w.table_rows[tbl]
        usable = [w.keep(c, by) for c, by in s.tests for x in design if x.kind == "index" and x.tables == (tbl,) and x.cols[0] == c]
        total += rows * min(usable) // 1000 if usable else rows
    needed, own = s.needed(), tuple(sorted(s.tables))
    return min([total, *(x.rows for x in design if x.kind == "view" and x.tables == own and needed <= set(x.cols))])


def whatif_cost(w: Workload, design: list[Structure]) -> int:
    return sum(n * query_cost(w, w.shapes[t], design) for t, n in w.counts.items())


def advise(w: Workload, kinds: set[str], evaluations: int, most: int = 8) -> tuple[list[Structure], int]:
    """(design, evaluations used): greedy choice while what-if evaluations last.

    Every look at one entry of the log under one candidate is an evaluation, so a longer log
    uses its budget up sooner; a round that is cut short picks from what it has seen, and a
    budget that ends before one candidate is through gives no design.
    """
    entries = sum(w.counts.values())
    left, design = evaluations, []
    rest = candidates(w, kinds)
    now = whatif_cost(w, design)
    while rest and len(design) < most and left >= entries:
        best: tuple | None = None
        for s in rest:
            if left < entries:
                break
            left -= entries
            cost = whatif_cost(w, [*design, s])
            if best is None or cost < best[0]:
                best = cost, s
        if best is None or best[0] >= now:
            break
        now = best[0]
        design.append(best[1])
        rest.remove(best[1])
    return design, evaluations - left


def summarised(w: Workload, picked: list[str]) -> Workload:
    """The workload of a summary: the shapes of its entries."""
    counts: dict[str, int] = {}
    for t in picked:
        counts[t] = counts.get(t, 0) + 1
    return Workload(w.shapes, counts, w.table_rows, w.distinct)


def optimal(w: Workload, kinds: set[str], most: int = 8) -> list[Structure]:
    """The design from one entry of each shape, with all the patience that it needs: what any advice is held against."""
    once = Workload(w.shapes, dict.fromkeys(w.counts, 1), w.table_rows, w.distinct)
    return advise(once, kinds, 1 << 60, most)[0]


def whatif_table(spark: SparkSession, log: DataFrame, w: Workload) -> DataFrame:
    """(kind, tbl, cols, cost): what the whole log costs under each candidate alone, joined and summed in Spark."""
    shapes = shape_table(log, sorted(w.table_rows))
    rows = F.broadcast(spark.createDataFrame(list(w.table_rows.items()), "tbl string, rows long"))  # one row per table
    base = shapes.select("mark", "n", F.explode("tables").alias("tbl")).join(rows, "tbl").groupBy("mark", "n").agg(F.sum("rows").alias("plain"))
    total = base.agg(F.sum(F.col("n") * F.col("plain")).alias("none"))
    tests = shapes.select("n", F.explode("tests").alias("t")).select("n", F.substring_index("t", " ", 1).alias("col"), F.substring_index("t", " ", -1).alias("by"))
    keeps = F.broadcast(spark.createDataFrame(sorted({(c, by, w.keep(c, by)) for s in w.shapes.values() for c, by in s.tests}), "col string, by string, keep long"))
    index = tests.join(keeps, ["col", "by"]).withColumn("tbl", F.substring_index("col", ".", 1)).join(rows, "tbl")
    index = index.groupBy("tbl", "col").agg(F.sum(F.col("n") * (F.col("rows") - F.expr("rows * keep div 1000"))).alias("saved")).select(F.lit("index").alias("kind"), "tbl", F.col("col").alias("cols"), "saved")
    views = F.broadcast(spark.createDataFrame([(",".join(x.tables), list(x.cols), x.rows) for x in candidates(w, {"view"})], "tbl string, held array<string>, size long"))
    needs = shapes.join(base.drop("n"), "mark").select("n", "plain", F.array_join(F.array_sort("tables"), ",").alias("tbl"), F.array_union("grouped", F.transform("tests", lambda t: F.substring_index(t, " ", 1))).alias("need"))
    usable = views.join(needs, "tbl").where(F.size(F.array_except("need", "held")) == 0)
    view = usable.groupBy("tbl", "held").agg(F.sum(F.col("n") * F.greatest(F.lit(0), F.col("plain") - F.col("size"))).alias("saved")).select(F.lit("view").alias("kind"), "tbl", F.array_join("held", ",").alias("cols"), "saved")
    return index.unionByName(view).crossJoin(F.broadcast(total)).select("kind", "tbl", "cols", (F.col("none") - F.col("saved")).alias("cost"))


def sweep(full: Workload, summary: Workload, kinds: set[str], budgets: list[int]) -> list[dict]:
    """Cost of the full log under the designs that either log leads to, by evaluation budget."""
    none = whatif_cost(full, [])
    out = []
    for b in budgets:
        from_full, _ = advise(full, kinds, b)
        from_summary, _ = advise(summary, kinds, b)
        out.append({"budget": b, "none": none, "full": whatif_cost(full, from_full), "summary": whatif_cost(full, from_summary)})
    return out


def design_table(spark: SparkSession, design: list[Structure]) -> DataFrame:
    return spark.createDataFrame([(s.kind, ",".join(s.tables), list(s.cols), s.rows) for s in design], "kind string, tbl string, cols array<string>, rows long")


def sorted_copy(df: DataFrame, column: str, path: str) -> DataFrame:
    """A real stand-in for an index: a copy in ranges of the column, sorted within them, whose min-max statistics prune row groups."""
    df.repartitionByRange(column).sortWithinPartitions(column).write.mode("overwrite").parquet(path)
    return df.sparkSession.read.parquet(path)


def measure(spark: SparkSession, texts: list[str], tables: dict[str, DataFrame]) -> float:
    """Seconds that a list of queries takes over the given tables, results discarded."""
    import time

    for name, df in tables.items():
        df.createOrReplaceTempView(name)
    t = time.perf_counter()
    for sql in texts:
        spark.sql(sql).write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t
