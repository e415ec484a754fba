"""Backward slices: from cells of a result to what of the inputs, the trace and the query they rest on.

A target lists result elements by the labels of the source elements behind them, with a mask per field, and says what holds for
all other elements: ``SKIP`` (anything), ``CLOSED`` (there are no others) or ``SAME`` (they stay as they are).

* An open target is answered from its labels alone: each generator's part of the label names the source elements, so the work is
  in the number of elements asked for, whatever the size of the tables.
* A closed target rests on every iteration: the conditions of all elements are demanded.  A run with a full recorded trace reads them
  from it; else elements are found per generator by semi-joins, and products are never formed (see ``runs.reached``).
* Bags inside aggregates and emptiness tests are not recorded: their members are found again.

Masks are small integers; 2 and 1 tell the inner and the outer part of a difference apart.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from backtrail.plans import compile as plan
from backtrail.plans.blocks import Block, Gen, Guard, aggregates, cost, used
from backtrail.plans.expr import Agg, Each, Empty, Expr, Field, Hole, If, IsEmpty, Let, Op, Record, Single, Table, Union, Var, Whole, children, rebuilt, render, uses
from backtrail.operators.runs import Run, guard_uses
from backtrail.sources.catalog import Catalog, dotted, given

SKIP, CLOSED, SAME = "skip", "closed", "same"
ROW = "m__row"
#: Targets up to so many rows are broadcast to what they select from.
SMALL = 100_000


def mask(name: str) -> str:
    return f"m_{name}"


def _parsed(block: Block, depths: dict[str, int], lbl: str) -> tuple | None:
    """The generators' label columns in a dotted label, or None if it is not of this block."""
    numbers, at, found = [int(x) for x in lbl.split(".") if x], 0, {}
    for part in block.parts:
        n = 1 if isinstance(part, int) else depths[part]
        piece = numbers[at : at + n]
        if len(piece) < n or (isinstance(part, int) and piece != [part]):
            return None
        found[part], at = piece, at + n
    return tuple(x for g in block.gens for x in found[g.var]) if at == len(numbers) else None


def _narrowed(run: Run, i: int, labels: list[tuple], only: str | None = None) -> tuple[Block, Catalog]:
    """A block and a catalog in which its generators, or the one named, range over the elements that a few label tuples name.

    Inner bags of aggregates still read whole tables.
    """
    block, cat = run.blocks[i], run.base
    small, at = cat, 0
    parts: dict[str, list[tuple]] = {}
    for g in block.gens:
        if only not in (None, g.var):
            continue
        n = len(cat.labels(g.table))
        parts.setdefault(g.table, []).extend(row[at : at + n] for row in labels)
        at += n
    for table, rows in parts.items():
        own, keys = cat[table], cat.labels(table)
        for j, k in enumerate(keys):
            values = sorted({r[j] for r in rows})
            own = own.filter(F.col(k).isin(values)) if len(values) <= 1000 else own.filter(F.col(k).between(values[0], values[-1]))
        small = small.replaced(f"{table} asked", own.join(F.broadcast(given(cat.spark, sorted(set(rows)), **{k: "long" for k in keys})), keys, "left_semi").select(*cat[table].columns))
    return replace(block, steps=tuple(replace(s, table=f"{s.table} asked") if isinstance(s, Gen) and only in (None, s.var) else s for s in block.steps)), small


def _value_at(run: Run, i: int, labels: list[tuple]) -> DataFrame:
    """Those elements of a block's result that a few label tuples name, computed from the source elements they name alone."""
    block, cat = run.blocks[i], run.base
    if not labels:
        return run.value_of(i).filter(F.lit(False))
    names = plan.all_labels(block, cat)
    if not names:
        return run.value_of(i)
    asked = F.broadcast(given(cat.spark, labels, **{c: "long" for c in names}))
    found = run.values[i] if i in run.values else plan.value(*_narrowed(run, i, labels))
    return found.join(asked, names, "left_semi").select(*found.columns)


def labels_in(run: Run, i: int, labels: list[str]) -> list[tuple]:
    """The label tuples of those dotted labels that have the form of a block's."""
    depths = {g.var: len(run.cat.labels(g.table)) for g in run.blocks[i].gens}
    return sorted({found for lbl in labels if (found := _parsed(run.blocks[i], depths, lbl)) is not None})


def value_at(run: Run, i: int, labels: list[str]) -> DataFrame:
    """Those elements of a block's result that a few dotted labels name."""
    return _value_at(run, i, labels_in(run, i, labels)).filter(F.col("lbl").isin(labels))


def values_at(run: Run, labels: list[str]) -> DataFrame:
    """The elements of the result that a few dotted labels name: ``lbl`` and fields."""
    parts = [value_at(run, i, labels).select("lbl", *[k for k, _ in b.fields()]) for i, b in enumerate(run.blocks)]
    return reduce(DataFrame.unionByName, parts)


def first_labels(run: Run, n: int = 1, by_number: bool = False) -> list[str]:
    """The first labels of the result, in the order of their texts or of the numbers in them.

    Both orders go by the parts of a label in turn (a dot sorts before digits).  So the first ``n`` elements lie among those of the
    first ``n`` elements of the first generator that reach the result, and only these are joined with the others.
    """
    found = []
    for i, block in enumerate(run.blocks):
        order = [p for p in block.parts if not isinstance(p, int)]
        if len(order) < 2 or i in run.values or {g.var for g in block.gens} != set(order):
            value = run.value_of(i)
        else:
            gen = next(g for g in block.gens if g.var == order[0])
            keys = [F.col(c) if by_number else F.col(c).cast("string") for c in plan.gen_labels(run.cat, gen)]
            least = [tuple(r) for r in run.reached(i, len(block.steps), gen).orderBy(*keys).limit(n).collect()]
            value = plan.value(*_narrowed(run, i, least, gen.var)) if least else run.value_of(i).filter(F.lit(False))
        by = F.split("lbl", r"\.").cast("array<long>") if by_number else F.col("lbl")
        found += [r[0] for r in value.select("lbl").orderBy(by).limit(n).collect()]
    return sorted(found, key=lambda lbl: [int(x) for x in lbl.split(".")] if by_number else lbl)[:n]


def _present(run: Run, i: int, labels: list[tuple]) -> set[tuple]:
    """Those of a few label tuples that are in a block's result, seen from the source elements they name alone."""
    block, cat = run.blocks[i], run.cat
    if not labels:
        return set()
    names = plan.all_labels(block, cat)
    if not names:
        return set(labels) if run.value_of(i).limit(1).count() else set()
    asked = given(cat.spark, labels, **{c: "long" for c in names})
    df = run.result_labels(i) if i in run.values else plan.frame(*_narrowed(run, i, labels)).select(*names)
    return {tuple(r) for r in df.join(F.broadcast(asked), names, "left_semi").distinct().collect()}


class _Local(dict):
    """Frames of given rows, made when something asks for them."""

    def __init__(self, run: Run, rows: dict[int, list[tuple]]):
        super().__init__()
        self.run, self.rows = run, rows

    def __missing__(self, i: int) -> DataFrame:
        block = self.run.blocks[i]
        kinds = {c: "long" for c in plan.all_labels(block, self.run.cat)} | {mask(k): "int" for k, _ in block.fields()} | {ROW: "int"}
        self[i] = given(self.run.cat.spark, self.rows[i], **kinds)
        return self[i]


@dataclass
class Target:
    """Per block: label columns, a mask per head field (``m_…``) and the row's own level ``m__row``."""

    run: Run
    frames: dict[int, DataFrame]
    rest: str = SKIP
    local: dict[int, list[tuple]] | None = None  # the frames' rows, where a few labels were given
    labels: list[str] | None = None  # the labels asked for, where a few were given
    asked: dict[int, DataFrame] | None = None  # of a closed target: the frames without the elements listed and skipped

    @classmethod
    def at(cls, run: Run, cells: dict[str, list[str]], level: int = 1) -> Target:
        """A few elements of the result by dotted label, each with its own fields; labels or fields that it lacks raise an error.

        A label spells out the source elements it was made of: only these are looked up, by their labels, to see that the element is
        there.  The slice of it then needs no look at the data.
        """
        if len(cells) > SMALL:
            raise ValueError(f"more than {SMALL} labels: use where()")
        local, strange = {}, set(cells)
        for i, block in enumerate(run.blocks):
            names = [k for k, _ in block.fields()]
            depths = {g.var: len(run.cat.labels(g.table)) for g in block.gens}
            parsed = {lbl: labels for lbl in cells if (labels := _parsed(block, depths, lbl)) is not None}
            there = _present(run, i, sorted(set(parsed.values())))
            found = [(lbl, labels) for lbl, labels in parsed.items() if labels in there]
            if unknown := sorted({k for lbl, _ in found for k in cells[lbl]} - set(names)):
                raise ValueError(f"no fields {unknown} in the result")
            strange -= {lbl for lbl, _ in found}
            local[i] = [(*labels, *[level if k in cells[lbl] else 0 for k in names], level) for lbl, labels in found]
        if strange:
            raise ValueError(f"not in the result: {sorted(strange)[:5]}")
        return cls(run, _Local(run, local), SKIP, local, list(cells))

    @classmethod
    def where(cls, run: Run, cond: Column | str, fields: list[str] | None = None, rest: str = SKIP, level: int = 1) -> Target:
        """Elements that satisfy a predicate over ``lbl`` and the fields, and these of their fields (all if None)."""
        frames = {}
        for i, block in enumerate(run.blocks):
            names = [k for k, _ in block.fields()]
            masks = [F.lit(level if fields is None or k in fields else 0).alias(mask(k)) for k in names]
            hit = run.value_of(i).filter(cond)
            frames[i] = hit.select(*plan.all_labels(block, run.cat), *masks, F.lit(level).alias(ROW))
        return cls(run, frames, rest)

    @classmethod
    def cells(cls, run: Run, cells: dict[str, list[str]], rest: str = SKIP, level: int = 1) -> Target:
        """Given elements by dotted label, each with its own fields; the rest of a record is skipped.

        They are computed from the source elements that their labels name, not from the whole result.
        """
        frames = {}
        for i, block in enumerate(run.blocks):
            names = [k for k, _ in block.fields()]
            asked = {k: [lbl for lbl, fs in cells.items() if k in fs] for k in names}
            hit = value_at(run, i, list(cells))
            masks = [F.when(F.col("lbl").isin(asked[k]) if asked[k] else F.lit(False), F.lit(level)).otherwise(F.lit(0)).alias(mask(k)) for k in names]
            frames[i] = hit.select(*plan.all_labels(block, run.cat), *masks, F.lit(level).alias(ROW))
        return cls(run, frames, rest, labels=list(cells))

    @classmethod
    def topk(cls, run: Run, n: int, by: str, fields: list[str] | None = None, ascending: bool = False) -> Target:
        """The first ``n`` elements by a field, ties by label."""
        order = F.col(by).asc() if ascending else F.col(by).desc()
        labels = [r[0] for r in run.value().orderBy(order, "lbl").limit(n).select("lbl").collect()]
        return cls.cells(run, {lbl: fields if fields is not None else list(dict(run.blocks[0].fields())) for lbl in labels})

    def closed(self) -> Target:
        """The same cells with every other element listed and skipped."""
        frames = {}
        for i, block in enumerate(self.run.blocks):
            labels = plan.all_labels(block, self.run.cat)
            names = [mask(k) for k, _ in block.fields()]
            everything = self.run.result_labels(i)
            hit = self.frames[i].select(*labels, *names)
            joined = everything.join(hit, labels, "left")
            frames[i] = joined.select(*labels, *[F.coalesce(m, F.lit(0)).alias(m) for m in names], F.lit(1).alias(ROW))
        return Target(self.run, frames, CLOSED, labels=self.labels, asked=dict(enumerate(self.frames[i] for i in range(len(self.run.blocks)))))

    def same(self) -> Target:
        """Everything as it is."""
        frames = {}
        for i, block in enumerate(self.run.blocks):
            labels = plan.all_labels(block, self.run.cat)
            frames[i] = self.run.result_labels(i).select(*labels, *[F.lit(1).alias(mask(k)) for k, _ in block.fields()], F.lit(1).alias(ROW))
        return Target(self.run, frames, SAME)


def difference(inner: Target, outer: Target) -> Target:
    """One target of both patterns: level 2 where the inner one asks, 1 where only the outer one does.

    The inner pattern lies below the outer one: its elements and fields are among the other's (see ``leq``).
    """
    frames = {}
    for i, block in enumerate(outer.run.blocks):
        labels = plan.all_labels(block, outer.run.cat)
        names = [*[mask(k) for k, _ in block.fields()], ROW]
        both = outer.frames[i].select(*labels, *names).unionByName(inner.frames[i].select(*labels, *[(F.col(m) * 2).alias(m) for m in names]))
        frames[i] = both.groupBy(*labels).agg(*[F.max(m).alias(m) for m in names])
    return Target(outer.run, frames, outer.rest)


def leq(inner: Target, outer: Target) -> DataFrame:
    """Elements or fields of the inner target that the outer one lacks; none if it lies below."""
    out = None
    for i, block in enumerate(outer.run.blocks):
        labels = plan.all_labels(block, outer.run.cat)
        names = [mask(k) for k, _ in block.fields()]
        other = outer.frames[i].select(*labels, *[F.col(m).alias(f"o{m}") for m in names])
        found = inner.frames[i].join(other, labels, "left").filter(reduce(lambda a, b: a | b, [F.col(m) > F.coalesce(f"o{m}", F.lit(-1)) for m in names]))
        rows = found.select(F.lit(i).alias("block"), dotted([F.col(c) for c in labels]).alias("lbl"))
        out = rows if out is None else out.unionByName(rows)
    return out


@dataclass
class Demand:
    """What a slice asks of one table: ``rows`` (label columns, ``m_<column>``), and what holds for elements not listed."""

    table: str
    rows: DataFrame
    rest: str
    columns: list[str]

    def cells(self, cat: Catalog) -> DataFrame:
        """The demanded elements with demanded values, others null."""
        keys = cat.labels(self.table)
        own = self.rows.select(*keys, *[F.col(mask(c)).alias(mask(c)) for c in self.columns])
        found = cat[self.table].join(own, keys)
        return found.select(*keys, *[F.when(F.col(mask(c)) > 0, F.col(c)).alias(c) for c in self.columns])

    def labelled(self) -> DataFrame:
        """``lbl`` and masks."""
        keys = [c for c in self.rows.columns if c.startswith("_l")]
        return self.rows.select(dotted([F.col(c) for c in keys]).alias("lbl"), *[F.col(mask(c)).cast("int").alias(mask(c)) for c in self.columns])


@dataclass
class Slice:
    run: Run
    target: Target
    inputs: dict[str, Demand]
    tight: bool = False
    stats: dict = field(default_factory=dict)


class _Demands:
    """Collects demands per table; several on one table are joined."""

    def __init__(self, cat: Catalog):
        self.cat, self.found = cat, {}

    def add(self, gen: Gen, df: DataFrame, masks: dict[str, Column], rest: str) -> None:
        keys = self.cat.labels(gen.table)
        names = plan.gen_labels(self.cat, gen)
        rows = df.select(*[F.col(n).alias(k) for n, k in zip(names, keys)], *[masks.get(c, F.lit(0)).cast("tinyint").alias(mask(c)) for c in self.cat.columns(gen.table)])
        self.found.setdefault(gen.table, []).append((rows, rest))

    def joined(self) -> dict[str, Demand]:
        out = {}
        for table, parts in self.found.items():
            keys, columns = self.cat.labels(table), self.cat.columns(table)
            rows = reduce(DataFrame.unionByName, [r for r, _ in parts])
            rows = rows.groupBy(*keys).agg(*[F.max(mask(c)).alias(mask(c)) for c in columns])
            rests = {r for _, r in parts}
            out[table] = Demand(table, rows, CLOSED if CLOSED in rests else SAME if SAME in rests else SKIP, columns)
        return out


def _highest(columns: list[Column]) -> Column:
    return F.greatest(*columns) if len(columns) > 1 else columns[0]


def _body_masks(block: Block, gen: Gen, with_guards: bool) -> dict[str, Column]:
    """Mask of each column of a generator, in terms of the target's masks."""
    asked: dict[str, list[Column]] = {}
    for name, e in block.fields():
        reads = used(e)
        for x in aggregates(e):
            for inner in x.bag.blocks:
                own = {g.var for g in inner.gens}
                reads |= {(g, c) for s in inner.guards for g, c in used(s.cond) if g not in own}
        for g, c in reads:
            if g == gen.var:
                asked.setdefault(c, []).append(F.col(mask(name)))
    if with_guards:
        for guard in block.guards:
            for g, c in guard_uses(guard):
                if g == gen.var:
                    asked.setdefault(c, []).append(F.col(ROW))
    return {c: _highest(columns) for c, columns in asked.items()}


def _inner_demands(into: _Demands, run: Run, outer: Block, rows: DataFrame, agg: Expr, level: Column, tight: bool, witness: bool) -> None:
    """Demand of an aggregate or emptiness test over its inner bag, for the outer iterations in ``rows``.

    Conditions of all inner elements are demanded, and values of members; with ``tight`` values that only are counted are not,
    and a bag that only must not be empty rests on one witness for each outer iteration.
    """
    cat = run.cat
    kept = plan.frame(Block(tuple(outer.gens)), cat) if not outer.guards else plan.frame(outer, cat)
    labels = plan.all_labels(outer, cat)
    kept = kept.join(rows.select(*labels, level.alias("__level")).filter("__level > 0"), labels)
    for block in agg.bag.blocks:
        inner, outside = plan.inner_parts(block)
        cond = reduce(lambda a, b: a & b, [plan.test_of(g) for g in outside], F.lit(True))
        members = kept.join(plan.frame(inner, cat), cond)
        any_outer = kept.agg(F.max("__level").alias("__any")).filter("__any is not null")
        for gen in block.gens:
            reads = {c for g, c in used(block.fields()[0][1]) if g == gen.var}
            tests = {c for s in block.guards for g, c in used(s.cond) if g == gen.var}
            if tight and witness:
                first = members.groupBy(*labels).agg(F.min(F.struct(*plan.gen_labels(cat, gen), "__level")).alias("w")).select("w.*")
                into.add(gen, first, {c: F.col("__level") for c in tests}, SKIP)
                continue
            everything = plan.source(cat, gen).select(*plan.gen_labels(cat, gen)).crossJoin(F.broadcast(any_outer))
            into.add(gen, everything, {c: F.col("__any") for c in tests}, CLOSED)
            if not (tight and (isinstance(agg, IsEmpty) or agg.kind == "count")):
                into.add(gen, members, {c: F.col("__level") for c in reads}, CLOSED)


def slice_inputs(run: Run, target: Target, tight: bool = False) -> dict[str, Demand]:
    """Demand on every table, without the trace."""
    if target.local is not None and not any(aggregates(b.head) or any(aggregates(g.cond) for g in b.guards) for b in run.blocks):
        return _local_inputs(run, target.local)
    into = _Demands(run.cat)
    for i, block in enumerate(run.blocks):
        rows, open_ = target.frames[i], target.rest == SKIP
        for gen in block.gens:
            at = block.steps.index(gen)
            rest = SKIP if open_ else CLOSED
            # The elements that a closed target lists and skips reach their generators, which are added below.
            own = rows if target.asked is None or not block.steps else target.asked[i]
            into.add(gen, own, _body_masks(block, gen, open_), rest)
            if not open_:  # elements and the columns of conditions, those of one step in one scan
                asked: dict[int, set[str]] = {at + 1: set()}
                for k, step in enumerate(block.steps):
                    if isinstance(step, Guard) and (columns := {c for g, c in guard_uses(step) if g == gen.var}):
                        asked.setdefault(k, set()).update(columns)
                for k, columns in asked.items():
                    into.add(gen, run.reached(i, k, gen), {c: F.lit(1) for c in columns}, rest)
        for name, e in block.fields():
            for x in aggregates(e):
                _inner_demands(into, run, block, rows, x, F.col(mask(name)), tight, False)
        for k, guard in enumerate(block.steps):
            for x in aggregates(guard.cond) if isinstance(guard, Guard) else ():
                inverse = isinstance(guard.cond, Op) and guard.cond.name == "not" and isinstance(guard.cond.args[0], IsEmpty)
                witness = inverse if guard.taken else isinstance(guard.cond, IsEmpty)
                if open_:
                    _inner_demands(into, run, block, rows, x, F.col(ROW), tight, witness)
                else:  # all iterations that meet the condition rest on it, whatever it says
                    before = Block(block.steps[:k])
                    _inner_demands(into, run, before, plan.frame(before, run.cat), x, F.lit(1), tight, False)
    return into.joined()


def _column_masks(block: Block) -> dict[str, dict[str, tuple[list[int], bool]]]:
    """Per generator and column: the fields that read it, by number, and whether a guard does."""
    out: dict = {g.var: {} for g in block.gens}
    for n, (_, e) in enumerate(block.fields()):
        for g, c in used(e):
            out[g].setdefault(c, ([], False))[0].append(n)
    for guard in block.guards:
        for g, c in guard_uses(guard):
            out[g][c] = (out[g].get(c, ([], False))[0], True)
    return out


def _local_inputs(run: Run, local: dict[int, list[tuple]]) -> dict[str, Demand]:
    found: dict[str, dict[tuple, dict[str, int]]] = {}
    for i, block in enumerate(run.blocks):
        reads, fields, at, places = _column_masks(block), len(block.fields()), 0, {}
        for g in block.gens:
            places[g.var] = slice(at, at := at + len(run.cat.labels(g.table)))
        for g in block.gens:
            rows = found.setdefault(g.table, {})
            for row in local[i]:
                masks = rows.setdefault(row[places[g.var]], {})
                for c, (names, guarded) in reads[g.var].items():
                    masks[c] = max([masks.get(c, 0), row[-1] if guarded else 0, *(row[at + n] for n in names)])
        assert all(len(row) == at + fields + 1 for row in local[i])
    out = {}
    for table, rows in found.items():
        keys, columns = run.cat.labels(table), run.cat.columns(table)
        data = [(*label, *[masks.get(c, 0) for c in columns]) for label, masks in sorted(rows.items())]
        out[table] = Demand(table, given(run.cat.spark, data, **{k: "long" for k in keys}, **{mask(c): "tinyint" for c in columns}), SKIP, columns)
    return out


def slice_trace(run: Run, target: Target, tight: bool = False) -> Slice:
    return Slice(run, target, slice_inputs(run, target, tight), tight)


def sliced_trace(s: Slice, among: DataFrame | None = None) -> DataFrame:
    """Kept iterations of every conditional as ``(site, lbl, branch)``; with ``among`` those whose site and label are in it."""
    out, numbers = None, s.run.numbers()
    if s.target.local is not None:
        rows = set()
        for i, block in enumerate(s.run.blocks):
            for k, step in enumerate(block.steps):
                if isinstance(step, Guard):
                    depth = sum(len(s.run.cat.labels(g.table)) for g in block.gens if block.steps.index(g) < k)
                    rows |= {(numbers[step.site], ".".join(map(str, r[:depth])), step.taken) for r in s.target.local[i]}
        return given(s.run.cat.spark, sorted(rows), site="int", lbl="string", branch="boolean")
    for i, block in enumerate(s.run.blocks):
        for k, step in enumerate(block.steps):
            if not isinstance(step, Guard):
                continue
            labels = [c for g in block.gens if block.steps.index(g) < k for c in plan.gen_labels(s.run.cat, g)]
            stored = s.run.branches(i, k)
            if s.target.rest == SKIP:
                df = s.target.frames[i].select(*labels).distinct()
                df = df.withColumn("branch", F.lit(step.taken)) if stored is None else s.run.branches_at(i, k, df.select(F.lit(numbers[step.site]).alias("site"), dotted([F.col(c) for c in labels]).alias("lbl")), s.run.level)
            elif stored is not None:
                df = (stored if among is None else s.run.branches_at(i, k, among, s.run.level)).select(*labels, "branch")
            else:
                passed = plan.frame(Block((*block.steps[:k], step)), s.run.cat).select(*labels).distinct().withColumn("__p", F.lit(True))
                before = plan.frame(block, s.run.cat, k).select(*labels).distinct()
                df = before.join(passed, labels, "left").select(*labels, (F.coalesce("__p", F.lit(False)) == F.lit(step.taken)).alias("branch"))
            rows = df.select(F.lit(numbers[step.site]).alias("site"), dotted([F.col(c) for c in labels]).alias("lbl"), "branch")
            out = rows if out is None else out.unionByName(rows)
    out = s.run.cat.spark.createDataFrame([], "site int, lbl string, branch boolean") if out is None else out.distinct()
    return out if among is None else out.join(among.select("site", "lbl").distinct(), ["site", "lbl"], "left_semi")


def slice_nodes(s: Slice) -> int:
    """Nodes of the kept trace, one per constructor, holes not counted."""
    run, total, shared = s.run, 0, set()
    for i, block in enumerate(run.blocks):
        rows, open_ = s.target.frames[i], s.target.rest == SKIP
        sums = rows.agg(F.count("*").alias("n"), *[F.sum((F.col(mask(k)) > 0).cast("int")).alias(k) for k, _ in block.fields()], F.sum((_highest([F.col(mask(k)) for k, _ in block.fields()]) > 0).cast("int")).alias("__any")).first()
        if open_ and not sums["n"]:
            continue
        for site, mark in block.path:
            if mark.startswith("union") and site not in shared:
                shared.add(site)
                total += 1
        for k, step in enumerate(block.steps):
            key = (block.parts[: 1 if block.parts and isinstance(block.parts[0], int) else 0], step.site)
            if key in shared:
                continue
            shared.add(key)
            before_gens = [g for g in block.gens if block.steps.index(g) < k]
            labels = [c for g in before_gens for c in plan.gen_labels(run.cat, g)]
            before = (rows.select(*labels).distinct().count() if labels else 1) if open_ else (run.reach_count(i, k) if k else 1)
            if isinstance(step, Gen):
                total += 2 * before
            else:
                total += before * (1 + cost(step.cond))
                if not open_ and step.taken:
                    total += before - run.reach_count(i, k + 1)
        total += sums["n"] + (0 if block.plain else sums["__any"] or 0)  # singletons, records with a field
        if not isinstance(block.head, Whole):
            total += sum((sums[k] or 0) * cost(e) for k, e in block.fields())
    return total


# --- slices of the query -----------------------------------------------------------------------------------------------


def query_marks(run: Run, target: Target) -> dict[int, tuple[int, int, int]]:
    """Site number to (kept, then used, else used), as levels; one small row per block comes to the driver."""
    numbers, marks = run.numbers(), {}

    def note(site: int, level: int, then: int = 0, other: int = 0) -> None:
        a = marks.get(numbers[site], (0, 0, 0))
        marks[numbers[site]] = tuple(map(max, a, (level, then, other)))

    def inside(steps: tuple, rows: DataFrame | None, e: Expr, level: int) -> None:
        """Marks of the bags that an expression aggregates, which stay the same: the branches that any of their iterations takes."""
        for agg in aggregates(e):
            for inner in agg.bag.blocks:
                for site, _ in inner.path:
                    note(site, level)
                for m, step in enumerate(inner.steps):
                    if isinstance(step, Guard):
                        here = [_any(run, (*steps, *inner.steps[:m], replace(step, taken=t)), rows) for t in (True, False)]
                        note(step.site, level, *(level * int(x) for x in here))

    for i, block in enumerate(run.blocks):
        if target.local is not None:
            best = [max(column) for column in zip(*target.local[i])] or [None] * (len(block.fields()) + 1)
            got = dict(zip([k for k, _ in block.fields()] + ["row"], best[-len(block.fields()) - 1 :]))
        else:
            got = target.frames[i].agg(F.max(ROW).alias("row"), *[F.max(mask(k)).alias(k) for k, _ in block.fields()]).first()
        level = got["row"] or 0
        rows = target.frames[i].filter(F.col(ROW) > 0).select(*plan.all_labels(block, run.cat)) if target.rest == SKIP and plan.all_labels(block, run.cat) else None
        if target.rest != SKIP:
            for k, step in enumerate(block.steps):
                if isinstance(step, Guard):
                    before, after = run.reach_count(i, k) if k else 1, run.reach_count(i, k + 1)
                    used_, other = int(after > 0), int(before > after)
                    note(step.site, int(before > 0), used_ if step.taken else other, other if step.taken else used_)
                else:
                    note(step.site, 1)
            level = level or 1
        if not level:
            continue
        for site, mark in block.path:
            note(site, level, level if mark == "then" and got["row"] else 0, level if mark == "else" and got["row"] else 0)
        for k, step in enumerate(block.steps):
            if isinstance(step, Guard):
                inside(block.steps[:k], rows, step.cond, level)
        for name, e in block.fields():
            if got[name]:
                note(_field_site(run.expr, block, name), got[name])
                inside(block.steps, rows, e, got[name])
    return marks


def _any(run: Run, steps: tuple, rows: DataFrame | None) -> bool:
    """Whether an iteration passes the steps, among those of the given outer ones."""
    df = plan.frame(Block(steps), run.cat)
    if rows is not None:
        labels = [c for c in rows.columns if c in df.columns]
        df = df.join(rows.select(*labels), labels, "left_semi") if labels else df
    return df.limit(1).count() > 0


def _field_site(e: Expr, block: Block, name: str) -> int:
    single = next(s for s, m in reversed(block.path) if m == "single")

    def find(x: Expr):
        from backtrail.plans.expr import children

        if x.site == single:
            return dict(x.item.fields)[name].site if isinstance(x.item, Record) else x.item.site
        return next((f for c in children(x) if (f := find(c)) is not None), None)

    return find(e)


def slice_query(run: Run, target: Target) -> Expr:
    """The query with holes where the target needs nothing.

    Of a bag that is named or nested as a source, the fields stay that what is kept of its readers reads.  A bag that is aggregated
    stays the same, but for branches that none of its iterations takes.
    """
    marks, numbers = query_marks(run, target), run.numbers()
    mark = lambda e: marks.get(numbers[e.site], (0, 0, 0))

    def scalar(e: Expr) -> Expr:
        if isinstance(e, (Agg, IsEmpty)):
            return rebuilt(e, [keep(e.bag, {"*"})])
        parts = children(e)
        found = [scalar(c) for c in parts]
        return e if all(a is b for a, b in zip(parts, found)) else rebuilt(e, found)

    def keep(e: Expr, wanted: set[str] | None = None) -> Expr:
        """``wanted``: fields of the bag's elements that are read, all with ``*``; None for the result, where the target says."""
        match e:
            case Empty() | Table() | Var():
                return e
            case Let(var=v, bound=b, body=c):
                body = keep(c, wanted)
                read = uses(body, v)
                if not mark(e)[0]:
                    return Hole()
                bound = Hole() if not read else keep(b, read) if isinstance(b, (Each, Union, If, Single, Empty, Let)) else scalar(b)
                return rebuilt(e, [bound, body])
        if not mark(e)[0]:
            return Hole()
        match e:
            case If(cond=c, then=t, other=o):
                _, a, b = mark(e)
                return rebuilt(e, [scalar(c), keep(t, wanted) if a else Hole(), keep(o, wanted) if b else Hole()])
            case Single(item=Record(fields=fields) as item):
                needed = lambda k, v: mark(v)[0] if wanted is None else "*" in wanted or k in wanted
                return rebuilt(e, [rebuilt(item, [scalar(v) if needed(k, v) else Hole() for k, v in fields])])
            case Single(item=x):
                return rebuilt(e, [scalar(x)])
            case Union(left=a, right=b):
                return rebuilt(e, [keep(a, wanted), keep(b, wanted)])
            case Each(var=v, source=s, body=b):
                body = keep(b, wanted)
                return rebuilt(e, [keep(s, uses(body, v)), body])
        return scalar(e)

    return keep(run.expr)


def leq_expr(a: Expr, b: Expr) -> bool:
    """Whether one partial query has no more than the other; a hole lies below everything."""
    if isinstance(a, Hole):
        return True
    x, y = children(a), children(b)
    return type(a) is type(b) and len(x) == len(y) and all(map(leq_expr, x, y))


def join_expr(a: Expr, b: Expr) -> Expr:
    """The least partial query above both; both come from one query."""
    if isinstance(a, Hole):
        return b
    if isinstance(b, Hole):
        return a
    return rebuilt(a, [join_expr(x, y) for x, y in zip(children(a), children(b))])


def fill(e: Expr, chooser, bag: bool = True) -> Expr:
    """A partial query with every hole filled: scalars by ``chooser()``, bags by the empty bag."""
    match e:
        case Hole():
            return Empty() if bag else chooser()
        case If(cond=c, then=t, other=o):
            return rebuilt(e, [fill(c, chooser, False), fill(t, chooser, bag), fill(o, chooser, bag)])
        case Let(bound=b, body=c):
            return rebuilt(e, [fill(b, chooser, not isinstance(b, (Hole, Op, Field, Record))), fill(c, chooser, bag)])
        case Union() | Each() | Agg() | IsEmpty():
            return rebuilt(e, [fill(c, chooser, True) for c in children(e)])
    return rebuilt(e, [fill(c, chooser, False) for c in children(e)])


def marks_frame(run: Run, target: Target) -> DataFrame:
    """``(site, kept, then_used, else_used)`` of every site of the query."""
    marks = query_marks(run, target)
    rows = [(n, *marks.get(n, (0, 0, 0))) for n in sorted(run.numbers().values())]
    return given(run.cat.spark, rows, site="int", kept="int", then_used="int", else_used="int")


# --- differences -------------------------------------------------------------------------------------------------------


def sliced_run(outer: Target) -> Run:
    """The run over what the outer slice keeps of the inputs: other cells are null, and of an open slice other elements gone."""
    run, cat = outer.run, outer.run.cat
    for name, d in slice_inputs(run, outer).items():
        cat = cat.replaced(name, d.cells(run.cat).select(*run.cat[name].columns))
    return Run(run.expr, cat, run.blocks, "on_demand", "taken")


def diff_inputs(inner: Target, outer: Target, one_pass: bool = True) -> dict[str, DataFrame]:
    """Per table the cells ``(lbl, column, level)``: 2 if the inner slice has them, 1 if only the outer one does.

    In one pass, both slices at once by levels; else the inner slice is taken from the outer one.
    """
    if one_pass:
        parts = slice_inputs(outer.run, difference(inner, outer))
        return {t: melted(d) for t, d in parts.items()}
    cut = sliced_run(outer)
    large, small = slice_inputs(outer.run, outer), slice_inputs(cut, Target(cut, inner.frames, inner.rest))
    out = {}
    for t, d in large.items():
        own = melted(d).select("lbl", "column", F.lit(1).alias("a"))
        other = melted(small[t]).select("lbl", "column", F.lit(1).alias("b"))
        out[t] = own.join(other, ["lbl", "column"], "left").select("lbl", "column", F.when(F.col("b").isNotNull(), 2).otherwise(1).alias("level"))
    return out


def melted(d: Demand) -> DataFrame:
    """Demanded cells one by one as ``(lbl, column, level)``."""
    wide = d.labelled()
    cells = F.array(*[F.struct(F.lit(c).alias("column"), F.col(mask(c)).alias("level")) for c in d.columns])
    return wide.select("lbl", F.explode(cells).alias("x")).select("lbl", "x.column", "x.level").filter("level > 0")


def diff_query(inner: Target, outer: Target) -> DataFrame:
    """Level of every site: 2 in both partial queries, 1 only in the outer one, 0 in neither."""
    return marks_frame(outer.run, difference(inner, outer))


def render_diff(inner: Target, outer: Target) -> str:
    """The outer partial query with the parts in brackets that the inner one lacks."""
    run = outer.run
    numbers, marks = run.numbers(), query_marks(run, difference(inner, outer))
    partial = slice_query(run, outer)
    boxed = lambda e, text: f"[{text}]" if marks.get(numbers.get(e.site, 0), (2,))[0] == 1 else text

    def show(e: Expr) -> str:
        match e:
            case Record(fields=fields):
                return "<" + ", ".join(f"{k}: {boxed(v, render(v))}" for k, v in fields) + ">"
            case Single(item=x):
                return "{" + show(x) + "}"
            case If(cond=c, then=t, other=o):
                return f"if {render(c)} then {show(t)} else {show(o)}"
            case Union(left=a, right=b):
                return f"({show(a)} ∪ {show(b)})"
            case Each(var=v, source=s, body=b):
                return f"∪{{{show(b)} | {v} ∈ {show(s)}}}"
            case Let(var=v, bound=b, body=c):
                return f"let {v} = {show(b)} in {show(c)}"
        return render(e)

    return show(partial)


def diff_trace(inner: Target, outer: Target) -> DataFrame:
    """Kept iterations of the outer slice, with level 2 where the inner slice, taken from the outer one, keeps them too."""
    cut = sliced_run(outer)
    a = sliced_trace(slice_trace(outer.run, outer))
    b = sliced_trace(slice_trace(cut, Target(cut, inner.frames, inner.rest))).withColumn("__i", F.lit(2))
    return a.join(b, ["site", "lbl", "branch"], "left").select("site", "lbl", "branch", F.coalesce("__i", F.lit(1)).alias("level"))
