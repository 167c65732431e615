"""Carrying the columns that an operator does not need past it.

Edge cases: names are compared as Spark compares them, without regard to case; names with dots
or quotes are taken as they stand; a table of needed columns only carries nothing; nulls,
repeated rows and empty tables pass as they are.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, functions as F


def quoted(name: str) -> Column:
    """The column of exactly this name, dots and quotes included."""
    return F.col("`" + name.replace("`", "``") + "`")


def carry(df: DataFrame, needed: list[str]) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """A table of the needed columns and one struct with all others, and a function that undoes it.

    An operator may add columns of any name to the packed table, drop rows or repeat them; the
    undoing function returns the columns of ``df`` with their own values, in their own order.
    """
    wanted = {n.lower(): n for n in needed}
    others = [c for c in df.columns if c.lower() not in wanted]
    row = F.struct(*(quoted(c).alias(f"c{i}") for i, c in enumerate(others))) if others else F.lit(None).cast("int")
    packed = df.select(*(quoted(c).alias(wanted[c.lower()]) for c in df.columns if c.lower() in wanted), row.alias("carried_row"))

    def unpack(out: DataFrame, added: list[str] = []) -> DataFrame:  # noqa: B006
        """The columns of ``df``; columns in ``added`` follow under their names with op_ before."""
        at = {c: f"carried_row.c{i}" for i, c in enumerate(others)}
        own = [F.col(at[c]).alias(c) if c in at else F.col(wanted[c.lower()]).alias(c) for c in df.columns]
        return out.select(*own, *(F.col(c).alias(f"op_{c}") for c in added))

    return packed, unpack
