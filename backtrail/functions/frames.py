"""Patterns of flat bags as DataFrames: label columns, a mask per column, and what holds for elements not listed.

Every literal of a legal pattern equals the actual value, so a mask says all: 0 skipped, 1 kept.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.operators.slicing import CLOSED, SAME, SKIP, Demand, mask
from backtrail.sources.catalog import Catalog, dotted

_JOIN_REST = {(SKIP, SKIP): SKIP, (SAME, SAME): SAME}
_PLUS_ORDER = (SKIP, SAME, CLOSED)


def keys_of(d: Demand) -> list[str]:
    return sorted((c for c in d.rows.columns if c.startswith("_l")), key=lambda c: int(c[2:]))


def join(a: Demand, b: Demand) -> tuple[Demand, DataFrame]:
    """The least demand above both, and the labels that a closed side excludes (none if the join exists)."""
    keys, columns = keys_of(a), a.columns
    left = a.rows.select(*keys, *[F.col(mask(c)).alias(f"a_{c}") for c in columns], F.lit(1).alias("__a"))
    right = b.rows.select(*keys, *[F.col(mask(c)).alias(f"b_{c}") for c in columns], F.lit(1).alias("__b"))
    both = left.join(right, keys, "full")
    default = lambda rest: F.lit(1 if rest == SAME else 0)
    masks = [F.greatest(F.coalesce(f"a_{c}", default(a.rest)), F.coalesce(f"b_{c}", default(b.rest))).cast("int").alias(mask(c)) for c in columns]
    excluded = (F.col("__a").isNull() & F.lit(a.rest == CLOSED)) | (F.col("__b").isNull() & F.lit(b.rest == CLOSED))
    rest = CLOSED if CLOSED in (a.rest, b.rest) else _JOIN_REST.get((a.rest, b.rest), SAME)
    return Demand(a.table, both.select(*keys, *masks), rest, columns), both.filter(excluded).select(*keys)


def plus(a: Demand, b: Demand) -> Demand:
    """Disjoint union; labels of the two sides must be prefix-disjoint."""
    return Demand(a.table, a.rows.unionByName(b.rows), min((a.rest, b.rest), key=_PLUS_ORDER.index), a.columns)


def harden(d: Demand) -> Demand:
    return Demand(d.table, d.rows.select(*keys_of(d), *[F.lit(1).alias(mask(c)) for c in d.columns]), SAME if d.rest == SKIP else d.rest, d.columns)


def under(d: Demand, label: tuple) -> Demand:
    """Elements below a label; its columns are taken off, the others renumbered."""
    keys = keys_of(d)
    hit = reduce(lambda x, y: x & y, [F.col(k) == v for k, v in zip(keys, label)], F.lit(True))
    left = keys[len(label) :]
    return Demand(d.table, d.rows.filter(hit).select(*[F.col(k).alias(f"_l{i}") for i, k in enumerate(left)], *[mask(c) for c in d.columns]), d.rest, d.columns)


def restrict(d: Demand, code: DataFrame) -> Demand:
    """Elements whose label extends one of a prefix code, given as its leading label columns."""
    return Demand(d.table, d.rows.join(code.distinct(), code.columns, "left_semi").select(*d.rows.columns), d.rest, d.columns)


def prepend(d: Demand, label: tuple) -> Demand:
    keys = keys_of(d)
    named = [F.lit(v).cast("long").alias(f"_l{i}") for i, v in enumerate(label)] + [F.col(k).alias(f"_l{len(label) + i}") for i, k in enumerate(keys)]
    return Demand(d.table, d.rows.select(*named, *[mask(c) for c in d.columns]), d.rest, d.columns)


def equiv_violations(d: Demand, a: Catalog, b: Catalog) -> DataFrame:
    """Where two catalogs differ as far as a demand goes: ``(lbl, reason)``; no rows if they are equivalent under it."""
    keys = a.labels(d.table)
    kept = [c for c in d.columns]
    have = [c for c in kept if c in b[d.table].columns]
    x = a[d.table].select(*keys, *[F.col(c).alias(f"a_{c}") for c in kept], F.lit(1).alias("__a"))
    y = b[d.table].select(*keys, *[F.col(c).alias(f"b_{c}") for c in have], F.lit(1).alias("__b"))
    both = d.rows.withColumn("__d", F.lit(1)).join(x, keys, "full").join(y, keys, "full")
    listed = F.col("__d").isNotNull()
    wrong = [F.when(F.col(mask(c)) > 0, ~F.col(f"a_{c}").eqNullSafe(F.col(f"b_{c}")) if c in have else F.lit(True)).otherwise(F.lit(False)) for c in kept]
    differs = [~F.col(f"a_{c}").eqNullSafe(F.col(f"b_{c}")) if c in have else F.lit(True) for c in kept]
    some = lambda tests: reduce(lambda p, q: p | q, tests)
    inside = F.when(F.col("__a").isNull() | F.col("__b").isNull(), F.lit("missing")).when(some(wrong), F.lit("changed"))
    outside = {SKIP: F.lit(None).cast("string"), CLOSED: F.lit("unlisted"), SAME: F.when(F.col("__a").isNull() | F.col("__b").isNull() | some(differs), F.lit("changed"))}[d.rest]
    return both.select(dotted([F.col(k) for k in keys]).alias("lbl"), F.when(listed, inside).otherwise(outside).alias("reason")).filter("reason is not null")


def leq_violations(a: Demand, b: Demand) -> DataFrame:
    """Cells that the first demand asks and the second does not."""
    keys = keys_of(a)
    other = b.rows.select(*keys, *[F.col(mask(c)).alias(f"b_{c}") for c in b.columns], F.lit(1).alias("__b"))
    default = F.lit(1 if b.rest == SAME else 0)
    more = reduce(lambda x, y: x | y, [F.col(mask(c)) > F.coalesce(f"b_{c}", default) for c in a.columns])
    return a.rows.join(other, keys, "left").filter(more | (F.col("__b").isNull() & F.lit(b.rest == CLOSED))).select(*keys)


def at_unit(d: Demand) -> DataFrame:
    """Masks of the element that a singleton's demand has, at the empty label."""
    if keys_of(d):
        raise ValueError("the empty label has no columns")
    return d.rows.select(*[mask(c) for c in d.columns])


def proj(d: Demand, column: str) -> Demand:
    """What is asked of one field of the elements."""
    return Demand(d.table, d.rows.select(*keys_of(d), mask(column)), d.rest, [column])


def dom(d: Demand) -> DataFrame:
    """Labels that are listed."""
    return d.rows.select(*keys_of(d))


def join_env(a: dict[str, Demand], b: dict[str, Demand]) -> dict[str, Demand]:
    """Demands of two environments, table by table; a table that one does not name is skipped there."""
    return {t: join(a[t], b[t])[0] if t in a and t in b else a.get(t, b.get(t)) for t in dict.fromkeys([*a, *b])}


def equiv_env(demands: dict[str, Demand], a: Catalog, b: Catalog) -> DataFrame:
    """Where two catalogs differ as far as the demands go: ``(source_table, lbl, reason)``."""
    parts = [equiv_violations(d, a, b).select(F.lit(t).alias("source_table"), "lbl", "reason") for t, d in demands.items()]
    return reduce(DataFrame.unionByName, parts)


def materialize(d: Demand, cat: Catalog) -> DataFrame:
    """The demand with the values that stand in the table: ``lbl`` and columns, null where skipped."""
    keys = cat.labels(d.table)
    return d.cells(cat).select(dotted([F.col(k) for k in keys]).alias("lbl"), *d.columns)
