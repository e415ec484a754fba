"""Blocks to DataFrames.

A block is a join of its generators with its guards as filters; Catalyst turns equalities into hash or merge joins, pushes the
rest down and prunes columns, label columns too where nobody reads them.  Aggregates inside a block are grouped by what
they correlate on before they are joined.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from backtrail.plans.blocks import Block, Gen, Guard, aggregates, used
from backtrail.plans.expr import Agg, Const, Expr, Field, IsEmpty, Op, Record, Var
from backtrail.sources.catalog import Catalog, dotted

_OPS = {
    "+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "/": lambda a, b: F.try_divide(a, b),
    "=": lambda a, b: a == b, "<>": lambda a, b: a != b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b,
    "and": lambda a, b: a & b, "or": lambda a, b: a | b, "not": lambda a: ~a, "if": lambda c, a, b: F.when(c, a).otherwise(b),
    "abs": F.abs, "sqrt": F.sqrt, "cents": lambda a: F.round(a * 100).cast("long"), "hash": lambda a: F.xxhash64(a),
    "isnull": lambda a: a.isNull(), "contains": lambda a, b: F.contains(a, b),
}
_AGGS = {"sum": F.sum, "count": lambda _: F.count(F.lit(1)), "min": F.min, "max": F.max, "avg": F.avg}


def column_name(gen: str, column: str) -> str:
    return f"{gen}__{column}"


def column(e: Expr, lifted: dict | None = None) -> Column:
    """A resolved scalar as a Column; ``lifted`` holds the columns of its aggregates."""
    match e:
        case Const(value=v):
            return F.lit(v)
        case Field(of=Var(name=g), name=c):
            return F.col(f"`{column_name(g, c)}`")
        case Field(of=of, name=c):
            return column(of, lifted).getField(c)
        case Op(name=n, args=args, fn=fn):
            return (fn or _OPS[n])(*[column(a, lifted) for a in args])
        case Record(fields=fields):
            return F.struct(*[column(v, lifted).alias(k) for k, v in fields])
        case Agg() | IsEmpty():
            return lifted[id(e)]
    raise TypeError(e)


def source(cat: Catalog, gen: Gen) -> DataFrame:
    df = cat[gen.table]
    return df.select(*[F.col(f"`{c}`").alias(column_name(gen.var, c)) for c in df.columns])


def gen_labels(cat: Catalog, gen: Gen) -> list[str]:
    return [column_name(gen.var, c) for c in cat.labels(gen.table)]


def _joined(df: DataFrame | None, other: DataFrame) -> DataFrame:
    return other if df is None else df.crossJoin(other)


def inner_parts(block: Block) -> tuple[Block, list[Guard]]:
    """An inner block without the guards that use outside generators; and these."""
    own = {g.var for g in block.gens}
    steps, outside = [], []
    for step in block.steps:
        for s in conjuncts(step):
            (outside if isinstance(s, Guard) and {g for g, _ in used(s.cond)} - own else steps).append(s)
    return Block(tuple(steps), block.parts, block.head, block.path), outside


def conjuncts(step) -> list:
    """A taken guard as one guard for each operand of its conjunction: for execution only, demands keep it whole."""
    if isinstance(step, Guard) and step.taken and isinstance(step.cond, Op) and step.cond.name == "and":
        return [g for a in step.cond.args for g in conjuncts(Guard(step.site, a, True, step.depth))]
    return [step]


def _equal_sides(guard: Guard, own: set[str]) -> tuple[Expr, Expr] | None:
    """``(inside, outside)`` of an equality between an inner and an outer expression."""
    match guard.cond:
        case Op(name="=", args=(a, b)) if guard.taken:
            for x, y in ((a, b), (b, a)):
                gx, gy = {g for g, _ in used(x)}, {g for g, _ in used(y)}
                if gx and gx <= own and gy and not gy & own:
                    return x, y
    return None


def test_of(guard: Guard, lifted: dict | None = None) -> Column:
    cond = column(guard.cond, lifted)  # null counts as false; a filter drops it, so equalities stay join keys
    return cond if guard.taken else ~F.coalesce(cond, F.lit(False))


def _emptiness(df: DataFrame, cat: Catalog, test: IsEmpty, empty: bool) -> DataFrame:
    """Rows of ``df`` for which the inner bag is empty, or, of one block, is not."""
    for block in test.bag.blocks:
        inner, outside = inner_parts(block)
        cond = reduce(lambda a, b: a & b, [test_of(g) for g in outside], F.lit(True))
        df = df.join(frame(inner, cat), cond, "left_anti" if empty else "left_semi")
    return df


def _label_names(df: DataFrame) -> list[str]:
    """Label columns of all generators that a frame has met: they tell its rows apart."""
    return [c for c in df.columns if c.split("__", 1)[-1].startswith("_l") and c.split("__", 1)[-1][2:].isdigit()]


def _grouped(agg: Expr, cat: Catalog) -> tuple[DataFrame, list[str], list[Expr]] | None:
    """Values of an inner bag of one block that correlates by equalities alone, keyed by what it correlates on."""
    if len(agg.bag.blocks) != 1:
        return None
    block = agg.bag.blocks[0]
    inner, outside = inner_parts(block)
    sides = [_equal_sides(g, {x.var for x in inner.gens}) for g in outside]
    if not all(sides):
        return None
    keys = [f"__k{i}" for i in range(len(sides))]
    return frame(inner, cat).select(*[column(x).alias(k) for k, (x, _) in zip(keys, sides)], _value(block).alias("__v")), keys, [y for _, y in sides]


def _value(block: Block) -> Column:
    return column(block.fields()[0][1])


def _with_aggregate(df: DataFrame, cat: Catalog, agg: Expr, n: int) -> tuple[DataFrame, Column]:
    """``df`` with the aggregate of its inner bag in a column; an emptiness test counts.

    Where the bag correlates by equalities, it is grouped by what it correlates on and joined.  Any other correlation, and bags of
    several blocks, join members to the labels of the rows they belong to and group by these.
    """
    name, kind = f"__agg{n}", "count" if isinstance(agg, IsEmpty) else agg.kind
    if not agg.bag.blocks:
        return df.withColumn(name, F.lit(0) if kind in ("sum", "count") else F.lit(None)), _finished(agg, F.col(name))
    if (found := _grouped(agg, cat)) is not None:
        rows, keys, outer = found
        grouped = rows.groupBy(*keys).agg(_AGGS[kind](F.col("__v")).alias(name))
        cond = reduce(lambda a, b: a & b, [column(y) == grouped[k] for k, y in zip(keys, outer)], F.lit(True))
        return df.join(grouped, cond, "left").drop(*keys), _finished(agg, F.col(name))
    labels, rows = _label_names(df), None
    reads = {column_name(*x) for block in agg.bag.blocks for g in inner_parts(block)[1] for x in used(g.cond)} & set(df.columns)
    for block in agg.bag.blocks:
        inner, outside = inner_parts(block)
        cond = reduce(lambda a, b: a & b, [test_of(g) for g in outside], F.lit(True))
        members = df.select(*dict.fromkeys([*labels, *sorted(reads)])).join(frame(inner, cat), cond).select(*labels, _value(block).alias("__v"))
        rows = members if rows is None else rows.unionByName(members)
    kept = [f"__of{i}" for i in range(len(labels))]
    grouped = rows.groupBy(*[F.col(c).alias(k) for c, k in zip(labels, kept)]).agg(_AGGS[kind](F.col("__v")).alias(name))
    cond = reduce(lambda a, b: a & b, [F.col(c) == F.col(k) for c, k in zip(labels, kept)], F.lit(True))
    return df.join(grouped, cond, "left").drop(*kept), _finished(agg, F.col(name))


def _finished(agg: Expr, found: Column) -> Column:
    if isinstance(agg, IsEmpty):
        return F.coalesce(found, F.lit(0)) == 0
    return F.coalesce(found, F.lit(0)) if agg.kind in ("sum", "count") else found


def with_aggregates(df: DataFrame, cat: Catalog, e: Expr) -> tuple[DataFrame, dict]:
    lifted = {}
    for x in aggregates(e):
        df, lifted[id(x)] = _with_aggregate(df, cat, x, x.site)
    return df, lifted


def guarded(df: DataFrame, cat: Catalog, guard: Guard) -> DataFrame:
    """Rows that take the guard's branch; operands of a conjunction that test no bag go first."""
    for part in sorted(conjuncts(guard), key=lambda g: bool(aggregates(g.cond))):
        test, taken = part.cond, part.taken
        if isinstance(test, Op) and test.name == "not" and isinstance(test.args[0], IsEmpty):
            test, taken = test.args[0], not taken
        if isinstance(test, IsEmpty) and (taken or len(test.bag.blocks) == 1):
            df = _emptiness(df, cat, test, taken)
            continue
        before = df.columns
        df, lifted = with_aggregates(df, cat, part.cond)
        df = df.filter(test_of(part, lifted)).select(*before)
    return df


def frame(block: Block, cat: Catalog, steps: int | None = None, start: DataFrame | None = None) -> DataFrame:
    """All columns of the generators, in iterations that pass the first ``steps`` steps."""
    df = start
    for step in block.steps[:steps]:
        if isinstance(step, Gen):
            df = _joined(df, source(cat, step)) if start is None or step.var not in {c.split("__")[0] for c in df.columns} else df
        else:
            df = guarded(df if df is not None else cat.spark.range(1).select(F.lit(1).alias("__unit")), cat, step)
    return df if df is not None else cat.spark.range(1).select(F.lit(1).alias("__unit"))


def frame_count(block: Block, cat: Catalog) -> int:
    """Number of iterations that pass a block: elements alike in all that its guards read are counted first, then joined once."""
    if any(aggregates(g.cond) for g in block.guards) or len(block.gens) < 2:
        return frame(block, cat).count()
    small, steps, reads = cat, [], {x for g in block.guards for x in used(g.cond)}
    for step in block.steps:
        if isinstance(step, Gen):
            columns = sorted({c for g, c in reads if g == step.var})
            small = small.replaced(f"{step.var} alike", cat[step.table].groupBy(*columns).agg(F.count("*").alias("__n")))
            step = replace(step, table=f"{step.var} alike")
        steps.append(step)
    sizes = reduce(lambda a, b: a * b, [F.col(column_name(g.var, "__n")).cast("decimal(38,0)") for g in block.gens])
    return int(frame(Block(tuple(steps)), small).agg(F.sum(sizes)).first()[0] or 0)


def label_parts(block: Block, cat: Catalog) -> list[Column]:
    gens = {g.var: g for g in block.gens}
    return [x for p in block.parts for x in ([F.lit(p)] if isinstance(p, int) else [F.col(c) for c in gen_labels(cat, gens[p])])]


def all_labels(block: Block, cat: Catalog) -> list[str]:
    return [c for g in block.gens for c in gen_labels(cat, g)]


def beforehand(block: Block, cat: Catalog) -> tuple[Block, Catalog]:
    """The block with opaque steps over one generator's element as columns of its table: applied once an element, not once a combination.

    What only such a step reads, a page's text say, then stays out of the join.  The elements are dealt out behind the steps: otherwise
    a broadcast join would apply them where a combination is put together.
    """
    if len(block.gens) < 2 or block.head is None or any(aggregates(e) for e in (block.head, *(g.cond for g in block.guards))):
        return block, cat
    tables, found = {g.var: g.table for g in block.gens}, {}

    def moved(e: Expr) -> Expr:
        match e:
            case Op(fn=fn) if fn is not None and len(of := {g for g, _ in used(e)}) == 1 and of <= set(tables):
                gen = of.pop()
                name = next((n for n, x in found.setdefault(gen, {}).items() if _same(x, e)), f"__step{len(found[gen])}")
                found[gen].setdefault(name, e)
                return Field(Var(gen), name)
            case Op(args=args):
                return replace(e, args=tuple(map(moved, args)))
            case Record(fields=fields):
                return replace(e, fields=tuple((k, moved(v)) for k, v in fields))
        return e

    guards = {id(s): replace(s, cond=moved(s.cond)) for s in block.guards}
    head = moved(block.head)
    if not found:
        return block, cat
    steps = []
    for step in block.steps:
        if isinstance(step, Gen) and step.var in found:
            own = source(cat, step).select("*", *[column(e).alias(column_name(step.var, n)) for n, e in found[step.var].items()])
            table = f"{step.var} beforehand"
            reads = {column_name(*x) for e in (head, *(g.cond for g in guards.values())) for x in used(e) if x[0] == step.var} | set(gen_labels(cat, step))
            own = own.select(*[F.col(f"`{c}`").alias(c[len(column_name(step.var, "")) :]) for c in own.columns if c in reads])
            cat = cat.replaced(table, own).spread(table)
            step = replace(step, table=table)
        steps.append(guards.get(id(step), step))
    return replace(block, steps=tuple(steps), head=head), cat


def _same(a: Expr, b: Expr) -> bool:
    """Whether two steps over one generator's element are the same function of the same arguments."""
    match a, b:
        case Op(), Op():
            return a.name == b.name and a.fn is b.fn and len(a.args) == len(b.args) and all(map(_same, a.args, b.args))
        case Field(), Field():
            return a.name == b.name and _same(a.of, b.of)
        case Var(), Var():
            return a.name == b.name
        case Const(), Const():
            return type(a.value) is type(b.value) and a.value == b.value
    return False


def value(block: Block, cat: Catalog) -> DataFrame:
    """``lbl``, the label columns of every generator, and the head's fields."""
    block, cat = beforehand(block, cat)
    df, lifted = with_aggregates(frame(block, cat), cat, block.head)
    return df.select(dotted(label_parts(block, cat)).alias("lbl"), *all_labels(block, cat), *[column(v, lifted).alias(k) for k, v in block.fields()])


def scalar(e: Expr, cat: Catalog) -> DataFrame:
    """A scalar query as one row ``value``."""
    unit = cat.spark.range(1).select(F.lit(1).alias("__unit"))
    df, lifted = with_aggregates(unit, cat, e)
    return df.select(column(e, lifted).alias("value"))
