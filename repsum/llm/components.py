"""Connected components by alternating large and small stars.

Each round is two aggregations with their joins back, over a table of edges that only
shrinks toward stars; nothing is collected but whether it has got there. Rounds are written
to the shared folder, so lineage stays short and a lost executor costs one round at most.

Edge cases: a link of a node with itself, a null end, a repeated or reversed link adds nothing;
an empty table of links has no nodes; a chain of any length settles in a number of rounds that
grows with the logarithm of its length.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from repsum.plans.scratch import materialise


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def _unsettled(edges: DataFrame) -> bool:
    """Whether some node still points to two nodes, or to a node that points on."""
    ends = edges.select(F.col("u").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(edges.select(F.col("v").alias("node"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    sums = ends.groupBy("node").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return not sums.where("up > 1 or (up = 1 and down = 1)").isEmpty()


def connected_components(links: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """(node, root) for every node of a link, root being its component's smallest node."""
    edges = materialise(_small_star(links.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u <> v")), "edges")
    for _ in range(rounds):
        if not _unsettled(edges):
            break
        edges = materialise(_small_star(_large_star(edges)), "stars")
    else:
        raise RuntimeError("components did not settle")
    ends = edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return ends.unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
