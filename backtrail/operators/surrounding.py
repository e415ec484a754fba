"""Demand rules of operators outside the query language: as-of joins, windows, top-k.

Each says what of its inputs the asked rows of a result rest on, as demands on the tables (outer joins and grouping sets are written in
the language itself, see ``plans.expr``; bags in columns and generators of rows are registered as tables of their own, see
``operators.nested``).  ``asked`` has the label columns of the asked rows; it joins, and is never collected.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from backtrail.operators.slicing import CLOSED, SKIP, Demand, mask
from backtrail.sources.catalog import Catalog


def _demand(cat: Catalog, table: str, parts: list[tuple[DataFrame, list[str]]], rest: str) -> Demand:
    keys, columns, rows = cat.labels(table), cat.columns(table), None
    for df, asked in parts:
        own = df.select(*keys, *[F.lit(int(c in asked)).cast("tinyint").alias(mask(c)) for c in columns])
        rows = own if rows is None else rows.unionByName(own)
    if len(parts) > 1:
        rows = rows.groupBy(*keys).agg(*[F.max(mask(c)).alias(mask(c)) for c in columns])
    return Demand(table, rows, rest, columns)


def window_demand(cat: Catalog, table: str, asked: DataFrame, partition: list[str], order: list[str], values: list[str]) -> dict[str, Demand]:
    """A function over a window of a partition: the partition's rows with their order and values; the partition column of every row.

    Any other row could join the partition, so its partition column is demanded too.
    """
    df, keys = cat[table], cat.labels(table)
    own = df.join(asked, keys, "left_semi").select(*partition).distinct()
    members = df.join(own, partition, "left_semi")
    return {table: _demand(cat, table, [(members, [*partition, *order, *values]), (df, partition)], CLOSED)}


def topk_demand(cat: Catalog, table: str, order: list, by: list[str], k: int, fields: list[str]) -> dict[str, Demand]:
    """The first ``k`` rows of a table: the sort columns of all rows, and the fields of the chosen ones."""
    df = cat[table]
    return {table: _demand(cat, table, [(df.orderBy(*order).limit(k), [*by, *fields]), (df, by)], CLOSED)}


def asof_demand(cat: Catalog, left: str, right: str, asked: DataFrame, keys: list[str], at: str, values: list[str]) -> dict[str, Demand]:
    """Left rows with the last right row of their keys at or before them: the asked rows' keys and time, the values of the row found,
    and keys and time of every right row, since any other one could come between."""
    mine, all_keys = cat[left].join(asked, cat.labels(left), "left_semi"), cat.labels(right)
    marked = cat[right].select(*keys, F.col(at), F.struct(*all_keys).alias("__found"), F.lit(0).alias("__side"))
    wanted = mine.select(*keys, F.col(at), F.lit(None).cast(marked.schema["__found"].dataType).alias("__found"), F.lit(1).alias("__side"))
    w = Window.partitionBy(*keys).orderBy(at, "__side", "__found").rowsBetween(Window.unboundedPreceding, 0)
    found = marked.unionByName(wanted).withColumn("__last", F.last("__found", ignorenulls=True).over(w)).filter("__side = 1 and __last is not null")
    chosen = found.select("__last.*").distinct()
    return {left: _demand(cat, left, [(mine, [*keys, at])], SKIP), right: _demand(cat, right, [(chosen, [*keys, at, *values]), (cat[right], [*keys, at])], CLOSED)}
