"""Nested results: records that hold bags, shredded into flat queries.

A bag inside a record is not built inside rows.  Every level of the result is a flat query of its own: where a head holds a bag, the
bag's query takes the head's place, so that its elements are labelled by their parent's label followed by their own.  A level is
thus traced, sliced and replayed like any flat query, sources and conditions shared with the levels above; demands and partial
queries of the levels are joined.  Children find their parent by the beginning of their label, of known length.

A table that holds a bag in a column is shredded the same way, when it is registered (:func:`register_nested`).
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.operators.replay import SCHEMA, replay
from backtrail.operators.runs import Run, numbered, trace, trace_rows
from backtrail.operators.slicing import CLOSED, SAME, SKIP, Demand, Target, join_expr, mask, slice_inputs, slice_query, slice_trace, sliced_trace
from backtrail.plans.blocks import Block
from backtrail.plans.expr import Const, Each, Empty, Expr, Field, Hole, If, Let, Record, Single, Union, Var, children, each, rebuilt, table, when
from backtrail.sources.catalog import Catalog

#: Path of the outermost bag.
ROOT = ()


def is_bag(e: Expr) -> bool:
    match e:
        case Each() | Single() | Union() | Empty():
            return True
        case If(then=a, other=b):
            return is_bag(a) or is_bag(b)
        case Let(body=b):
            return is_bag(b)
    return False


def _heads(e: Expr) -> list[Single]:
    """Singletons that make the elements of a bag, not those of its sources."""
    match e:
        case Single():
            return [e]
        case Each(body=b) | Let(body=b):
            return _heads(b)
        case If(then=a, other=b) | Union(left=a, right=b):
            return _heads(a) + _heads(b)
    return []


def _at_heads(e: Expr, change) -> Expr:
    """The bag with ``change(head)`` in place of every singleton that makes its elements."""
    match e:
        case Single():
            return change(e)
        case Each(source=s, body=b):
            return rebuilt(e, [s, _at_heads(b, change)])
        case Let(bound=v, body=b):
            return rebuilt(e, [v, _at_heads(b, change)])
        case If(cond=c, then=a, other=b):
            return rebuilt(e, [c, _at_heads(a, change), _at_heads(b, change)])
        case Union(left=a, right=b):
            return rebuilt(e, [_at_heads(a, change), _at_heads(b, change)])
    return e


def _scalars(head: Single) -> Expr:
    """The singleton without its bags; an element of bags alone keeps that it is there."""
    if not isinstance(head.item, Record):
        return head
    kept = tuple((k, v) for k, v in head.item.fields if not is_bag(v))
    if len(kept) == len(head.item.fields):
        return head
    item = Record(kept or (("there", Const(True)),))
    object.__setattr__(item, "site", head.item.site)
    return rebuilt(head, [item])


def shred(e: Expr, path: tuple = ROOT) -> dict[tuple, Expr]:
    """Path of every bag of a query's result to the flat query of its elements."""
    out = {path: _at_heads(e, _scalars)}
    names = dict.fromkeys(k for h in _heads(e) if isinstance(h.item, Record) for k, v in h.item.fields if is_bag(v))
    for name in names:
        inner = _at_heads(e, lambda h, n=name: dict(h.item.fields)[n])
        out |= shred(inner, (*path, name))
    return out


@dataclass
class NestedRun:
    """Runs of all levels by path; they share the catalog, and sites are numbered by the whole query."""

    expr: Expr
    cat: Catalog
    levels: dict[tuple, Run]

    def numbers(self) -> dict[int, int]:
        return numbered(self.expr)

    def parent_parts(self, path: tuple) -> int:
        """Parts of a parent's label; levels whose blocks label elements in unlike lengths have no such number."""
        found = {_parts(b, self.cat) for b in self.levels[path[:-1]].blocks}
        if len(found) != 1:
            raise ValueError(f"labels above {path} have unlike lengths")
        return found.pop()

    def frames(self) -> dict[tuple, DataFrame]:
        """The shredded result: for each level ``lbl``, ``parent`` (null at the root) and the scalar fields."""
        out = {}
        for path, run in self.levels.items():
            df = run.value()
            parent = F.array_join(F.slice(F.split("lbl", "\\."), 1, self.parent_parts(path)), ".") if path else F.lit(None).cast("string")
            out[path] = df.select("lbl", parent.alias("parent"), *[c for c in df.columns if c != "lbl"])
        return out

    def value(self) -> DataFrame:
        """The nested result: bags as arrays of records with their labels, in label order.

        An array is gathered per parent, so this form is for bags that fit a row; :meth:`frames` has no such bound.
        """
        frames = self.frames()

        def assembled(path: tuple) -> DataFrame:
            df = frames[path]
            for child in [p for p in frames if len(p) == len(path) + 1 and p[: len(path)] == path]:
                inner = assembled(child)
                rows = inner.groupBy("parent").agg(F.collect_list(F.struct(*[c for c in inner.columns if c != "parent"])).alias("__bag"))
                ordered = F.array_sort("__bag", lambda a, b: F.when(_order(a) < _order(b), -1).when(_order(a) > _order(b), 1).otherwise(0))
                bags = rows.select(F.col("parent").alias("__of"), ordered.alias(child[-1]))
                kind = bags.schema[child[-1]].dataType
                df = df.join(bags, F.col("lbl") == F.col("__of"), "left").drop("__of").withColumn(child[-1], F.coalesce(child[-1], F.array().cast(kind)))
            return df

        return assembled(ROOT).drop("parent")


def _order(row) -> DataFrame:
    return F.transform(F.split(row["lbl"], "\\."), lambda x: x.cast("long"))


def _parts(block: Block, cat: Catalog) -> int:
    gens = {g.var: g for g in block.gens}
    return sum(1 if isinstance(p, int) else len(cat.labels(gens[p].table)) for p in block.parts)


def trace_nested(e: Expr, cat: Catalog, mode: str = "on_demand", level: str = "taken", folder: str | None = None) -> NestedRun:
    """Evaluates and traces a query whose records may hold bags, level by level."""
    levels = {path: trace(flat, cat, mode, level, f"{folder}/{'.'.join(('root', *path))}" if folder else None) for path, flat in shred(e).items()}
    return NestedRun(e, cat, levels)


def _renumbered(run: Run, numbers: dict[int, int], rows: DataFrame) -> DataFrame:
    """Rows with sites as the whole query numbers them."""
    own = {n: numbers[site] for site, n in run.numbers().items() if site in numbers}
    found = F.create_map(*[F.lit(x) for pair in own.items() for x in pair])
    return rows.withColumn("site", found[F.col("site")])


def nested_trace_rows(run: NestedRun, level: str = "taken") -> DataFrame:
    """The dynamic trace of all levels as ``(site, lbl, branch)``; what levels share is there once."""
    numbers = run.numbers()
    return reduce(DataFrame.unionByName, [_renumbered(r, numbers, trace_rows(r, level)) for r in run.levels.values()]).distinct()


@dataclass
class NestedTarget:
    """A target for each level that is asked for; the levels between are asked for as far as their elements lead to it."""

    run: NestedRun
    targets: dict[tuple, Target] = field(default_factory=dict)

    @classmethod
    def where(cls, run: NestedRun, **asked) -> NestedTarget:
        """``level=(predicate, fields)`` with levels written as ``root``, ``root__orders``, ``root__orders__lines``."""
        paths = {"__".join(("root", *p)): p for p in run.levels}
        return cls(run, {paths[name]: Target.where(run.levels[paths[name]], *given) for name, given in asked.items()})


def _joined(cat: Catalog, parts: list[dict[str, Demand]]) -> dict[str, Demand]:
    """Demands of several levels on each table, joined."""
    out = {}
    for t in dict.fromkeys(t for p in parts for t in p):
        found = [p[t] for p in parts if t in p]
        rows = reduce(DataFrame.unionByName, [d.rows for d in found])
        keys, columns = cat.labels(t), found[0].columns
        rests = {d.rest for d in found}
        rows = rows.groupBy(*keys).agg(*[F.max(mask(c)).alias(mask(c)) for c in columns]) if len(found) > 1 else rows
        out[t] = Demand(t, rows, CLOSED if CLOSED in rests else SAME if SAME in rests else SKIP, columns)
    return out


def slice_nested_inputs(target: NestedTarget, tight: bool = False) -> dict[str, Demand]:
    return _joined(target.run.cat, [slice_inputs(t.run, t, tight) for t in target.targets.values()])


def slice_nested_trace(target: NestedTarget) -> DataFrame:
    numbers = target.run.numbers()
    return reduce(DataFrame.unionByName, [_renumbered(t.run, numbers, sliced_trace(slice_trace(t.run, t))) for t in target.targets.values()]).distinct()


def slice_nested_query(target: NestedTarget) -> Expr:
    """The partial query of the whole: each level's is put back where its bag stands, and they are joined."""
    return reduce(join_expr, [_embedded(target.run.expr, path, slice_query(t.run, t)) for path, t in target.targets.items()], Hole())


def _embedded(whole: Expr, path: tuple, partial: Expr) -> Expr:
    """A level's partial query as one of the whole query."""
    if not path:
        return _spread(whole, partial)
    name = path[0]

    def wrapped(e: Expr, p: Expr) -> Expr:
        """``e`` is the whole query; ``p`` the partial one in which the bag ``name`` stands in the head's place."""
        if isinstance(p, Hole):
            return p
        match e:
            case Single(item=Record(fields=fields) as item):
                own = dict(fields)[name]
                inner = _embedded(own, path[1:], p) if path[1:] else _spread(own, p)
                return rebuilt(e, [rebuilt(item, [inner if k == name else Hole() for k, _ in fields])])
            case Each() | Let():
                first, rest = children(p)
                return rebuilt(e, [first, wrapped(children(e)[1], rest)])
            case If():
                c, a, b = children(p)
                return rebuilt(e, [c, wrapped(e.then, a), wrapped(e.other, b)])
            case Union():
                a, b = children(p)
                return rebuilt(e, [wrapped(e.left, a), wrapped(e.right, b)])
        return p

    return wrapped(whole, partial)


def _spread(e: Expr, p: Expr) -> Expr:
    """A partial flat query with the fields that its heads lost to other levels, as holes."""
    if isinstance(p, Hole):
        return p
    match e:
        case Single(item=Record(fields=fields) as item) if isinstance(p, Single) and isinstance(p.item, Record):
            found = dict(p.item.fields)
            return rebuilt(e, [rebuilt(item, [found.get(k, Hole()) for k, _ in fields])])
        case Each() | Let():
            first, rest = children(p)
            return rebuilt(e, [first, _spread(children(e)[1], rest)])
        case If():
            c, a, b = children(p)
            return rebuilt(e, [c, _spread(e.then, a), _spread(e.other, b)])
        case Union():
            a, b = children(p)
            return rebuilt(e, [_spread(e.left, a), _spread(e.right, b)])
    return p


def replay_nested(run: NestedRun, cat: Catalog) -> DataFrame:
    """Failures ``(site, lbl, reason)`` of all levels on other tables."""
    numbers, parts = run.numbers(), []
    for r in run.levels.values():
        failures = replay(r, cat).failures
        missing, found = failures.filter("site = 0"), _renumbered(r, numbers, failures.filter("site > 0"))
        parts += [missing, found.select("site", "lbl", "reason")]
    return reduce(DataFrame.unionByName, parts).distinct() if parts else run.cat.spark.createDataFrame([], SCHEMA)


# --- nested sources ----------------------------------------------------------------------------------------------------


def child_table(name: str, column: str) -> str:
    return f"{name}.{column}"


def register_nested(cat: Catalog, name: str, df: DataFrame, keys: list[str], column: str) -> Catalog:
    """A table one of whose columns is an array of records: the table without it, and its elements as a table of their own.

    An element is labelled by its parent's label and its place in the array, from 1; ``of_0, of_1, …`` hold the parent's label.
    """
    cat.register(name, df.drop(column), keys)
    parent = [F.col(k).cast("long") for k in keys]
    spread = df.select(*[p.alias(f"of_{i}") for i, p in enumerate(parent)], F.posexplode(column).alias("__at", "__element"))
    labels = [F.col(f"of_{i}").alias(f"_l{i}") for i in range(len(keys))]
    fields = [F.col(f"__element.{f.name}").alias(f.name) for f in df.schema[column].dataType.elementType.fields]
    cat.tables[child_table(name, column)] = spread.select(*[f"of_{i}" for i in range(len(keys))], *fields, *labels, (F.col("__at") + 1).cast("long").alias(f"_l{len(keys)}"))
    return cat


def elements(of: str, name: str, keys: list[str], column: str, var: str, body: Expr) -> Expr:
    """The bag in a column of an element as a source: ``body`` for each of its elements, named ``var``."""
    same = [Field(Var(var), f"of_{i}").eq(Field(Var(of), k)) for i, k in enumerate(keys)]
    return each(var, table(child_table(name, column)), when(reduce(lambda a, b: a & b, same), body))
