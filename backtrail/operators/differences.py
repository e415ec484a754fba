"""Differences between the results of one query over two catalogs, without listing the results.

Whether an iteration passes, and what a field of its head is, depends on the columns that guards and head read of its elements and on
nothing else.  So each generator's elements are paired with the other catalog's by label and grouped by what both sides say in these
columns; only such groups are joined, every one with every other that it meets, and groups that differ are spread to labels again.
Nothing is left out: each result element of either side belongs to one combination of groups.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from backtrail.plans import compile as plan
from backtrail.plans.blocks import Block, Gen, Guard, aggregates, used
from backtrail.plans.expr import Expr
from backtrail.sources.catalog import Catalog, dotted

OTHER, THERE = "@other", "@there"


def plain(block: Block) -> bool:
    """Whether a block reads its generators alone: no bags inside conditions or the head."""
    return bool(block.gens) and not any(aggregates(e) for e in (*([block.head] if block.head is not None else []), *(g.cond for g in block.guards)))


class _Pairs:
    """A block's generators over one catalog, each element with what the other catalog has under its label."""

    def __init__(self, block: Block, cat: Catalog, other: Catalog, fields: tuple[tuple[str, Expr], ...] = ()):
        self.block, self.cat = block, cat
        reads = {x for e in (*(g.cond for g in block.guards), *(e for _, e in fields)) for x in used(e)}
        self.elements, self.columns = {}, {}
        for gen in block.gens:
            keys, columns = cat.labels(gen.table), sorted({c for g, c in reads if g == gen.var})
            theirs = other[gen.table].select(*keys, *[F.col(f"`{c}`").alias(c + OTHER) for c in columns], F.lit(True).alias(THERE))
            own = cat[gen.table].select(*keys, *[F.col(f"`{c}`") if c not in keys else F.col(c) for c in columns])
            self.columns[gen.var] = [*columns, *[c + OTHER for c in columns], THERE]
            self.elements[gen.var] = own.join(theirs, keys, "left").withColumn(THERE, F.coalesce(F.col(THERE), F.lit(False)))

    def groups(self) -> DataFrame:
        """Combinations of groups that pass the block's guards over the first catalog."""
        small, steps = self.cat, []
        for step in self.block.steps:
            if isinstance(step, Gen):
                small = small.replaced(f"{step.var} alike", self.elements[step.var].select(*[F.col(f"`{c}`") for c in self.columns[step.var]]).distinct())
                step = replace(step, table=f"{step.var} alike")
            steps.append(step)
        return plan.frame(Block(tuple(steps)), small)

    def there(self) -> Column:
        return reduce(lambda a, b: a & b, [F.col(f"`{plan.column_name(g.var, THERE)}`") for g in self.block.gens])

    def theirs(self, df: DataFrame) -> DataFrame:
        """The groups with the other catalog's columns under the names of the first one's."""
        out = []
        for gen in self.block.gens:
            for c in self.columns[gen.var]:
                name = plan.column_name(gen.var, c)
                if c.endswith(OTHER):
                    out.append(F.col(f"`{name}`").alias(plan.column_name(gen.var, c.removesuffix(OTHER))))
        return df.select(*out, *[c for c in df.columns if c.startswith("__")])

    def passes(self, cond: list[Guard]) -> Column:
        return reduce(lambda a, b: a & b, [F.coalesce(plan.test_of(g), F.lit(False)) for g in cond], F.lit(True))

    def spread(self, groups: DataFrame) -> DataFrame:
        """The label columns of all elements in combinations of groups."""
        df = groups
        for gen in self.block.gens:
            mine = self.elements[gen.var]
            mine = mine.select(*[F.col(f"`{c}`").alias(f"__e_{plan.column_name(gen.var, c)}") for c in mine.columns])
            cond = [F.col(f"`{n}`").eqNullSafe(F.col(f"`__e_{n}`")) for n in (plan.column_name(gen.var, c) for c in self.columns[gen.var])]
            df = df.join(mine, reduce(lambda a, b: a & b, cond))
        return df.select(*[F.col(f"`__e_{c}`").alias(c) for c in plan.all_labels(self.block, self.cat)])


def _marked(pairs: _Pairs, fields: tuple[tuple[str, Expr], ...] = ()) -> DataFrame:
    """Combinations of groups with ``__same``: whether the other catalog passes them too, and gives these fields the same values."""
    df = pairs.groups()
    df = df.withColumn("__row", F.struct(*[F.col(f"`{c}`") for c in df.columns])).withColumn("__there", pairs.there())
    df = df.withColumns({f"__v{n}": plan.column(e) for n, (_, e) in enumerate(fields)})
    df = pairs.theirs(df)
    same = [F.col("__there"), pairs.passes(pairs.block.guards), *[plan.column(e).eqNullSafe(F.col(f"__v{n}")) for n, (_, e) in enumerate(fields)]]
    return df.withColumn("__same", reduce(lambda a, b: a & b, same)).filter(~F.col("__same")).select("__row.*")


def lost(block: Block, cat: Catalog, other: Catalog, present: bool = False) -> DataFrame:
    """Label columns of iterations that pass over one catalog and not over another; ``present``: of elements that both have."""
    if len(block.gens) == 1 and not present:  # its elements are its iterations: nothing to group
        names = plan.all_labels(block, cat)
        return plan.frame(block, cat).select(*names).join(plan.frame(block, other).select(*names), names, "left_anti")
    pairs = _Pairs(block, cat, other)
    groups = _marked(pairs)
    return pairs.spread(groups.filter(pairs.there()) if present else groups)


def labels(blocks: list[Block], cat: Catalog, other: Catalog) -> DataFrame:
    """``lbl`` of the result elements over one catalog that the result over the other lacks."""
    return reduce(DataFrame.unionByName, [lost(b, cat, other).select(dotted(plan.label_parts(b, cat)).alias("lbl")) for b in blocks])


def rows(blocks: list[Block], cat: Catalog, other: Catalog) -> DataFrame:
    """``lbl`` of the result elements that one side lacks or has with another field; fields are compared one at a time."""
    out = []
    for b in blocks:
        if len(b.gens) == 1:
            names = [k for k, _ in b.fields()]
            sides = [plan.value(b, c).select("lbl", F.struct(*[F.col(f"`{k}`") for k in names]).alias(f"__{n}")) for n, c in enumerate((cat, other))]
            out.append(sides[0].join(sides[1], "lbl", "full").filter(~F.col("__0").eqNullSafe(F.col("__1"))).select("lbl"))
            continue
        out.append(labels([b], other, cat))
        for field in [(f,) for f in b.fields()] or [()]:
            pairs = _Pairs(b, cat, other, field)
            out.append(pairs.spread(_marked(pairs, field)).select(dotted(plan.label_parts(b, cat)).alias("lbl")))
    return reduce(DataFrame.unionByName, out).distinct()
