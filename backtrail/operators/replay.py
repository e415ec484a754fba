"""Replay of a trace on edited inputs.

A trace replays if every element that its comprehensions meet is known to it and every condition comes out as recorded.  Deleted
elements are no obstacle.  The recorded side are the run's trace frames and table labels where it has them (an eager run's do not
change with the tables), else the trace is derived from the run's own tables.  Both sides are compared by label joins, so nothing is
looped over on the driver and no product of generators is formed.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.operators import differences
from backtrail.operators.joins import broadcast_if_small
from backtrail.operators.runs import Run, components, guard_uses, place, trace
from backtrail.operators.slicing import Demand, Slice
from backtrail.plans import compile as plan
from backtrail.plans.blocks import Block, Gen, Guard, aggregates, used
from backtrail.sources.catalog import Catalog, Edits, dotted

SCHEMA = "site int, lbl string, reason string"


@dataclass
class Replay:
    failures: DataFrame  # (site, lbl, reason)
    run: Run | None

    @property
    def ok(self) -> bool:
        return self.failures.limit(1).count() == 0

    def value(self) -> DataFrame:
        if self.run is None:
            raise ValueError("a field that the trace needs is missing")
        return self.run.value()

    def by_reason(self) -> DataFrame:
        return self.failures.groupBy("reason").agg(F.count("*").alias("n"))


def restricted(cat: Catalog, demands: dict[str, Demand]) -> Catalog:
    """Tables cut down to the elements that an open slice lists; a table it skips altogether is empty."""
    out = cat
    for name in cat.tables:
        if name in demands:
            d = demands[name]
            out = out.replaced(name, cat[name].join(d.rows.select(*cat.labels(name)), cat.labels(name), "left_semi").select(*cat[name].columns))
    return out


def _columns(run: Run) -> set[tuple[str, str]]:
    out = set()
    for block in run.blocks:
        tables = {g.var: g.table for g in block.gens}
        reads = used(block.head).union(*[guard_uses(g) for g in block.guards])
        for e in (block.head, *(g.cond for g in block.guards)):
            for agg in aggregates(e):
                for inner in agg.bag.blocks:
                    tables |= {g.var: g.table for g in inner.gens}
                    reads = reads.union(used(inner.head), *[used(g.cond) for g in inner.guards])
        out |= {(tables[g], c) for g, c in reads}
    return out


def replay(run: Run, cat: Catalog, within: dict[str, Demand] | None = None, fields: set[tuple[str, str]] | None = None) -> Replay:
    """Replays a run's trace over another catalog, or a slice of it ``within`` the slice's demands.

    ``fields`` are the (table, column) pairs the trace needs; by default all that the query reads.
    """
    spark, numbers = run.cat.spark, run.numbers()
    need = fields if fields is not None else _columns(run)
    missing = sorted((t, c) for t, c in need if c not in cat.columns(t))
    if missing:
        return Replay(spark.createDataFrame([(0, f"{t}.{c}", "missing field") for t, c in missing], SCHEMA), None)
    old, new = run.cat, cat
    if within is not None:
        old, new = restricted(old, within), restricted(new, within)
    past = _Past(run, old, within is not None)
    for name in new.tables:  # fields that the slice does not need may be gone
        gone = [f for f in old[name].schema if f.name not in new[name].columns] if name in old.tables else []
        if gone:
            new = new.replaced(name, new[name].withColumns({f.name: F.lit(None).cast(f.dataType) for f in gone}))
    again = Run(run.expr, new, run.blocks, run.mode, run.level)
    parts, seen = [], set()
    for block in run.blocks:
        parts += _failures(block, 0, past, new, numbers, seen)
        for at, inner in _inner_blocks(block):
            parts += _failures(inner, at, past, new, numbers, seen)
    return Replay(_together(spark, parts), again)


def _together(spark, parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts).distinct() if parts else spark.createDataFrame([], SCHEMA)


class _Past:
    """What a trace says of the iterations it met; ``cut`` if only those within a slice count."""

    def __init__(self, run: Run, cat: Catalog, cut: bool = False):
        self.run, self.cat, self.cut = run, cat, cut
        self.frames = {place(run.blocks[i], k): df for (i, k), df in run.frames.items()}

    def labels_of(self, table: str) -> DataFrame:
        known = self.run.labels.get(table)
        return self.cat[table].select(*self.cat.labels(table)) if known is None or self.cut else known

    def passed(self, block: Block, k: int) -> DataFrame:
        """Label columns of the iterations that met the guard at ``k`` and satisfied its condition."""
        gens = [g for g in block.gens if block.steps.index(g) < k]
        labels = [c for g in gens for c in plan.gen_labels(self.cat, g)]
        stored = self.frames.get(place(block, k))
        if stored is None:
            return plan.frame(Block((*block.steps[:k], replace(block.steps[k], taken=True))), self.cat).select(*labels)
        found = stored.filter("branch").select(*labels)
        return _present(found, gens, self) if self.cut else found


def _present(df: DataFrame, gens: list[Gen], side) -> DataFrame:
    """Iterations all of whose elements one side has; ``side`` has ``labels_of``."""
    for g in gens:
        own = side.labels_of(g.table)
        names = plan.gen_labels(side.cat, g)
        df = df.join(own.select(*[F.col(a).alias(b) for a, b in zip(own.columns, names)]), names, "left_semi")
    return df


class _Now:
    """The tables that a trace is replayed on."""

    def __init__(self, cat: Catalog):
        self.cat = cat

    def labels_of(self, table: str) -> DataFrame:
        return self.cat[table].select(*self.cat.labels(table))


def _inner_blocks(block: Block) -> list[tuple[int, Block]]:
    """Blocks of the bags that a block's conditions and head aggregate, behind the steps that lead to them."""
    out = []
    for k, e in [*((k, s.cond) for k, s in enumerate(block.steps) if isinstance(s, Guard)), *([(len(block.steps), block.head)] if block.head is not None else [])]:
        for agg in aggregates(e):
            out += [(k, Block((*block.steps[:k], *inner.steps), head=inner.head)) for inner in agg.bag.blocks]
    return out


def _failures(block: Block, start: int, past: _Past, cat: Catalog, numbers: dict, seen: set, only: set[str] | None = None) -> list[DataFrame]:
    """Unknown labels, of the generators in ``only`` if it is given, and flipped branches of the steps from ``start`` on."""
    out, now = [], _Now(cat)
    for k, step in enumerate(block.steps):
        if k < start or place(block, k) in seen:
            continue
        seen.add(place(block, k))
        number = F.lit(numbers[step.site])
        if isinstance(step, Guard):
            out += [x.select(number.alias("site"), "lbl", F.lit("branch flipped").alias("reason")) for x in _flips(block, k, past, now)]
            continue
        if only is not None and step.var not in only:
            continue
        keys = cat.labels(step.table)
        strange = now.labels_of(step.table).join(past.labels_of(step.table), keys, "left_anti")
        for group in components(block, k):  # met only if an iteration gets there
            strange = strange.crossJoin(F.broadcast(plan.frame(Block(group), cat).limit(1).select(F.lit(1).alias("__any")))).drop("__any")
        out.append(strange.select(number.alias("site"), dotted([F.col(c) for c in keys]).alias("lbl"), F.lit("unknown label").alias("reason")))
    return out


def _flips(block: Block, k: int, past: _Past, now: _Now) -> list[DataFrame]:
    """Iterations present on both sides whose condition came out otherwise."""
    gens = [g for g in block.gens if block.steps.index(g) < k]
    labels = [c for g in gens for c in plan.gen_labels(now.cat, g)]
    passing = replace(block, steps=(*block.steps[:k], replace(block.steps[k], taken=True)), head=None)
    if gens and past.frames.get(place(block, k)) is None and not past.run.labels and not any(aggregates(g.cond) for g in passing.guards):
        return [differences.lost(passing, a, b, True).select(dotted([F.col(c) for c in labels]).alias("lbl")) for a, b in ((past.cat, now.cat), (now.cat, past.cat))]
    was, is_ = past.passed(block, k), plan.frame(Block((*block.steps[:k], replace(block.steps[k], taken=True))), now.cat).select(*labels)
    if not labels:  # one iteration: it passes on one side only
        one = was.limit(1).select(F.lit("").alias("lbl")), is_.limit(1).select(F.lit("").alias("lbl"))
        return [one[0].exceptAll(one[1]), one[1].exceptAll(one[0])]
    lost, gained = _present(was.join(is_, labels, "left_anti"), gens, now), _present(is_.join(was, labels, "left_anti"), gens, past)
    return [x.select(dotted([F.col(c) for c in labels]).alias("lbl")) for x in (lost, gained)]


def replay_slice(s: Slice, cat: Catalog) -> Replay:
    """Replays an open slice: elements outside it are of no concern."""
    need = {(t, c) for t, d in s.inputs.items() for c in d.columns if d.rows.filter(F.col(f"m_{c}") > 0).limit(1).count()}
    return replay(s.run, cat, s.inputs, need)


def can_replay(run: Run, edits: Edits) -> DataFrame:
    """Failures that edits would cause: those of :func:`replay`, found from the edited elements.

    An iteration can only fail if one of its elements is edited, or an element of a bag that its condition aggregates.  So each place
    where a query draws from the edited table is cut down in turn to the edited elements, all other places staying whole; and where a
    condition aggregates the table, the iterations that an edited element, before or after, belongs to are looked at.
    """
    spark, numbers = run.cat.spark, run.numbers()
    edited = run.cat.apply(edits)
    if edits.dropped:
        return replay(run, edited).failures
    touched = sorted({at for at, _, _ in edits.updates} | {at for at, _ in edits.inserts} | set(edits.deletes))
    if not touched:
        return spark.createDataFrame([], SCHEMA)
    name, keys = edits.table, run.cat.labels(edits.table)
    few = broadcast_if_small(spark.createDataFrame(touched, ", ".join(f"{k} long" for k in keys)))
    part = f"{name} edited"
    cut = lambda c: c.replaced(part, c[name].join(few, keys, "left_semi").select(*c[name].columns))
    old, new, parts = cut(run.cat), cut(edited), []

    def drawn(block: Block, k: int) -> Block:
        """The block with one generator cut to the edited elements."""
        return replace(block, steps=tuple(replace(s, table=part) if j == k else s for j, s in enumerate(block.steps)))

    def visit(block: Block, start: int) -> None:
        for k, step in enumerate(block.steps):
            if isinstance(step, Gen) and step.table == name:
                parts.extend(_failures(drawn(block, k), max(start, k), _Past(Run(run.expr, old, [], run.mode, run.level), old), new, numbers, set(), {step.var}))
            if isinstance(step, Guard) and aggregates(step.cond):
                parts.extend(_of_members(block, k, max(start, k)))

    def _of_members(block: Block, k: int, start: int) -> list[DataFrame]:
        before = Block(block.steps[:k])
        labels, found = plan.all_labels(before, old), []
        for at, inner in _inner_blocks(Block((*block.steps[: k + 1],))):
            if at != k:
                continue
            for m, step in enumerate(inner.steps[k:]):
                if isinstance(step, Gen) and step.table == name:
                    own, outside = plan.inner_parts(Block(drawn(inner, k + m).steps[k:], head=inner.head))
                    cond = reduce(lambda a, b: a & b, [plan.test_of(g) for g in outside], F.lit(True))
                    found += [plan.frame(before, c).join(plan.frame(own, c), cond).select(*labels) for c in (old, new)]
        if not found:
            return []
        a, b, variant = old, new, block
        if labels:
            hit = reduce(DataFrame.unionByName, found).distinct()
            for g in before.gens:
                alias, names = f"{g.table} of {g.var}", plan.gen_labels(old, g)
                own = hit.select(*[F.col(x).alias(y) for x, y in zip(names, old.labels(g.table))]).distinct()
                narrow = lambda c, t=g.table, o=own: c[t].join(o, c.labels(t), "left_semi").select(*c[t].columns)
                a, b = a.replaced(alias, narrow(a)), b.replaced(alias, narrow(b))
                variant = replace(variant, steps=tuple(replace(s, table=alias) if s is g else s for s in variant.steps))
        return _failures(variant, start, _Past(Run(run.expr, a, [], run.mode, run.level), a), b, numbers, set(), set())

    for block in run.blocks:
        visit(block, 0)
        for at, inner in _inner_blocks(block):
            visit(inner, at)
    return _together(spark, parts)


def recompute(s: Slice, cat: Catalog) -> DataFrame:
    """The part of the result that a slice explains, over another catalog."""
    return trace(s.run.expr, restricted(cat, s.inputs)).value()


def inside_demand(s: Slice, cat: Catalog) -> DataFrame:
    """Where another catalog leaves what a slice demands: ``(table, lbl, reason)``; no rows if it stays inside."""
    from backtrail.functions.frames import equiv_violations

    out = None
    for name, d in s.inputs.items():
        rows = equiv_violations(d, s.run.cat, cat).select(F.lit(name).alias("table"), "lbl", "reason")
        out = rows if out is None else out.unionByName(rows)
    return out
