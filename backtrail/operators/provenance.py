"""Other forms of provenance, to set beside slices: lineage, why, how, where, impact, trails, exports, redaction."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from backtrail.operators.joins import broadcast_if_small
from backtrail.operators.runs import Run, guard_uses
from backtrail.operators.slicing import Demand, Slice, mask
from backtrail.plans import compile as plan
from backtrail.plans.blocks import Block, Gen, used
from backtrail.plans.expr import Field, Var
from backtrail.sources.catalog import dotted


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _name(run: Run, block: Block, gen) -> Column:
    """A source element as ``table:label``."""
    return F.concat(F.lit(f"{gen.table}:"), dotted([F.col(c) for c in plan.gen_labels(run.cat, gen)]))


def labels_tell(run: Run) -> bool:
    """Whether dotted labels alone tell the result's elements apart, so that nothing made of them has to be compared: one block over
    different tables whose labels are not null and not repeated.  Reads each table's labels once."""
    if len(run.blocks) != 1:
        return False
    tables = [g.table for g in run.blocks[0].gens]
    if not tables or len(set(tables)) < len(tables):
        return False
    for table in tables:
        labels = [F.col(c) for c in run.base.labels(table)]
        whole = reduce(lambda a, b: a & b, [c.isNotNull() for c in labels])
        counted = run.base[table].groupBy(*labels).agg(F.count("*").alias("n"))
        if counted.filter((F.col("n") > 1) | ~whole).limit(1).count():
            return False
    return True


#: Column of a prepared table: an element's dotted label.
OWN = "__own"


def _texts(run: Run, gone: tuple[str, DataFrame] | None = None) -> DataFrame:
    """Of a run whose labels tell its elements apart: its elements' label parts, dotted, a column for each generator.

    Labels become text once an element of a table, before these meet; what a combination costs is to put its parts together.  Tables are
    dealt out by label, so that the pairs of a small file are not left to one task.  Elements of ``gone``, a table and its dotted labels
    in ``source``, are looked up as often.
    """
    (block,), cat = run.blocks, run.base
    if 0 in run.values:
        df = run.value_of(0).select(*[dotted([F.col(c) for c in plan.gen_labels(cat, g)]).alias(plan.column_name(g.var, OWN)) for g in block.gens])
        for gen in block.gens if gone else []:
            df = df.join(gone[1], F.col(plan.column_name(gen.var, OWN)) == gone[1]["source"], "left_anti") if gen.table == gone[0] else df
        return df
    steps = []
    for step in block.steps:
        if isinstance(step, Gen):
            name = f"{step.var} told"
            own = cat[step.table].withColumn(OWN, dotted([F.col(c) for c in run.base.labels(step.table)]))
            cat = cat.replaced(name, own.join(gone[1], F.col(OWN) == gone[1]["source"], "left_anti") if gone and step.table == gone[0] else own)
            if len(block.gens) > 1:
                cat = cat.spread(name)
                cat = cat.replaced(name, broadcast_if_small(cat[name]))
            step = replace(step, table=name)
        steps.append(step)
    return plan.frame(replace(block, steps=tuple(steps)), cat).select(*[plan.column_name(g.var, OWN) for g in block.gens])


def _whole(block: Block) -> list[Column]:
    """A label of ``_texts`` as pieces to be put together."""
    parts = [F.lit(str(p)) if isinstance(p, int) else F.col(plan.column_name(p, OWN)) for p in block.parts]
    return [x for p in parts for x in (F.lit("."), p)][1:]


def lineage(run: Run) -> DataFrame:
    """``(lbl, source_table, source)``: the source elements behind every result element; read off its label's parts."""
    if labels_tell(run):
        (block,), df = run.blocks, _texts(run)
        return _union([df.select(F.concat(*_whole(block)).alias("lbl"), F.lit(g.table).alias("source_table"), F.col(plan.column_name(g.var, OWN)).alias("source")) for g in block.gens])
    parts = []
    for i, block in enumerate(run.blocks):
        df = run.value_of(i)
        for gen in block.gens:
            parts.append(df.select("lbl", F.lit(gen.table).alias("source_table"), dotted([F.col(c) for c in plan.gen_labels(run.cat, gen)]).alias("source")))
    return _union(parts).distinct()


def witnesses(run: Run) -> DataFrame:
    """``(fields, witness)`` for every result element: the set of its source elements, sorted."""
    parts = []
    for i, block in enumerate(run.blocks):
        names = [_name(run, block, g) for g in block.gens]
        witness = F.array_sort(F.array_distinct(F.array(*names))) if names else F.array().cast("array<string>")
        parts.append(run.value_of(i).select(*[k for k, _ in block.fields()], witness.alias("witness")))
    return _union(parts)


def why(run: Run, minimal: bool = False) -> DataFrame:
    """``(fields, witness)``, distinct per result value; with ``minimal`` only witnesses that contain no other one of the value.

    A witness has no more elements than the query has generators, so its proper subsets are listed and looked up.
    """
    found = witnesses(run)
    fields = [c for c in found.columns if c != "witness"]
    rows = found.withColumn("witness", F.array_join("witness", " ")).distinct()
    if not minimal:
        return rows
    most = max((len(b.gens) for b in run.blocks), default=0)
    parts = F.split("witness", " ")
    subsets = [F.array_join(F.filter(F.array(*[F.get(parts, i) for i in chosen]), lambda x: x.isNotNull()), " ") for n in range(1, most) for chosen in combinations(range(most), n)]
    if not subsets:
        return rows
    spread = rows.select(*fields, "witness", F.explode(F.array_distinct(F.array(*subsets))).alias("__small")).filter("__small <> witness")
    same = [F.col(f"x.{c}").eqNullSafe(F.col(f"y.{c}")) for c in fields]
    hit = spread.alias("x").join(rows.alias("y"), reduce(lambda a, b: a & b, [*same, F.col("x.__small") == F.col("y.witness")]), "left_semi")
    drop = hit.select(*fields, "witness").distinct()
    cond = [F.col(f"x.{c}").eqNullSafe(F.col(f"y.{c}")) for c in [*fields, "witness"]]
    return rows.alias("x").join(drop.alias("y"), reduce(lambda a, b: a & b, cond), "left_anti")


def how(run: Run) -> DataFrame:
    """Polynomials, sparse: ``(fields, monomial, coefficient)`` per result value; a monomial keeps repeated factors."""
    parts = []
    for i, block in enumerate(run.blocks):
        names = [_name(run, block, g) for g in block.gens]
        monomial = F.array_join(F.array_sort(F.array(*names)), "*") if names else F.lit("1")
        parts.append(run.value_of(i).select(*[k for k, _ in block.fields()], monomial.alias("monomial")))
    rows = _union(parts)
    return rows.groupBy(*rows.columns).agg(F.count("*").alias("coefficient"))


def eval_semiring(polynomials: DataFrame, ring: str, costs: DataFrame | None = None) -> DataFrame:
    """``(fields, value)``: a polynomial's value with every source element 1 (``counting``), present (``boolean``), at its cost
    (``min_cost``; ``costs(name, cost)``, one each by default), or itself (``polynomial``, as text: for small results)."""
    fields = [c for c in polynomials.columns if c not in ("monomial", "coefficient")]
    if ring == "counting":
        return polynomials.groupBy(*fields).agg(F.sum("coefficient").alias("value"))
    if ring == "boolean":
        return polynomials.groupBy(*fields).agg((F.sum("coefficient") > 0).alias("value"))
    if ring == "min_cost":
        if costs is None:
            priced = polynomials.withColumn("__cost", F.when(F.col("monomial") == "1", 0).otherwise(F.size(F.split("monomial", "\\*"))).cast("long"))
        else:
            spread = polynomials.withColumn("name", F.explode(F.split("monomial", "\\*")))
            priced = spread.join(costs, "name", "left").groupBy(*fields, "monomial").agg(F.sum(F.coalesce("cost", F.lit(0))).alias("__cost"))
        return priced.groupBy(*fields).agg(F.min("__cost").alias("value"))
    if ring == "polynomial":
        term = F.when(F.col("coefficient") == 1, F.col("monomial")).otherwise(F.concat(F.col("coefficient").cast("string"), F.lit("*"), F.col("monomial")))
        return polynomials.groupBy(*fields).agg(F.array_join(F.array_sort(F.collect_list(term)), " + ").alias("value"))
    raise ValueError(ring)


def how_delete(run: Run, table: str, labels: DataFrame) -> DataFrame:
    """Result labels that survive the deletion of source elements, without running the query again; ``labels(source)``."""
    if labels_tell(run):  # an element is looked up once, not once for every label that it is a part of
        return _texts(run, (table, labels.distinct())).select(F.concat(*_whole(run.blocks[0])).alias("lbl"))
    gone = lineage(run).filter(F.col("source_table") == table).join(labels.distinct(), "source", "left_semi").select("lbl").distinct()
    return run.value().select("lbl").join(gone, "lbl", "left_anti")


def where(run: Run) -> DataFrame:
    """``(lbl, field, source_table, source, source_column)``: cells that were copied, not computed."""
    parts = []
    for i, block in enumerate(run.blocks):
        gens = {g.var: g for g in block.gens}
        for name, e in block.fields():
            match e:
                case Field(of=Var(name=g), name=c) if g in gens:
                    labels = dotted([F.col(x) for x in plan.gen_labels(run.cat, gens[g])])
                    parts.append(run.value_of(i).select("lbl", F.lit(name).alias("field"), F.lit(gens[g].table).alias("source_table"), labels.alias("source"), F.lit(c).alias("source_column")))
    return _union(parts) if parts else run.cat.spark.createDataFrame([], "lbl string, field string, source_table string, source string, source_column string")


def impact(run: Run, table: str, labels: DataFrame, column: str) -> DataFrame:
    """``(lbl, field)``: result cells that may change when a column of given elements does; field ``*`` is the element's presence.

    ``labels`` has the table's label columns.  Elements that are not in the result yet, but might come, are not listed.
    """
    parts = []
    for i, block in enumerate(run.blocks):
        for gen in block.gens:
            if gen.table != table:
                continue
            fields = [k for k, e in block.fields() if (gen.var, column) in used(e)]
            fields += ["*"] if any((gen.var, column) in guard_uses(g) for g in block.guards) else []
            if fields:
                own = labels.select(*[F.col(a).alias(b) for a, b in zip(run.cat.labels(table), plan.gen_labels(run.cat, gen))])
                hit = run.value_of(i).join(own, plan.gen_labels(run.cat, gen), "left_semi")
                parts.append(hit.select("lbl", F.explode(F.array(*map(F.lit, fields))).alias("field")))
    return _union(parts).distinct() if parts else run.cat.spark.createDataFrame([], "lbl string, field string")


def equal_except_at(a: DataFrame, b: DataFrame, labels: DataFrame) -> DataFrame:
    """Labels outside the given ones at which two results differ; none if they are equal elsewhere."""
    fields = [c for c in a.columns if c != "lbl"]
    x = a.join(labels, "lbl", "left_anti").select("lbl", F.struct(*fields).alias("__x"))
    y = b.join(labels, "lbl", "left_anti").select("lbl", F.struct(*fields).alias("__y"))
    return x.join(y, "lbl", "full").filter(~F.col("__x").eqNullSafe(F.col("__y"))).select("lbl")


# --- graphs ------------------------------------------------------------------------------------------------------------


def export_graph(run: Run) -> DataFrame:
    """Edges ``(node, relation, to)``: a result element was made by a step, which used source elements."""
    if labels_tell(run):
        (block,), df = run.blocks, _texts(run)
        whole = _whole(block)
        made, step = F.concat(F.lit("result:"), *whole), F.concat(F.lit("step0:"), *whole)
        parts = [df.select(made.alias("node"), F.lit("generated_by").alias("relation"), step.alias("to"))]
        for gen in block.gens:
            name = F.concat(F.lit(f"{gen.table}:"), F.col(plan.column_name(gen.var, OWN)))
            parts.append(df.select(step.alias("node"), F.lit("used").alias("relation"), name.alias("to")))
        return _union(parts)
    parts = []
    for i, block in enumerate(run.blocks):
        df = run.value_of(i)
        made, step = F.concat(F.lit("result:"), F.col("lbl")), F.concat(F.lit(f"step{i}:"), F.col("lbl"))
        parts.append(df.select(made.alias("node"), F.lit("generated_by").alias("relation"), step.alias("to")))
        for gen in block.gens:
            parts.append(df.select(step.alias("node"), F.lit("used").alias("relation"), _name(run, block, gen).alias("to")))
    return _union(parts).distinct()


def export_triples(run: Run) -> DataFrame:
    """A run as ``(subject, predicate, object)``: fields of results, and where they come from."""
    values = []
    for i, block in enumerate(run.blocks):
        df = run.value_of(i)
        for name, _ in block.fields():
            values.append(df.select(F.concat(F.lit("result:"), F.col("lbl")).alias("subject"), F.lit(f"field {name}").alias("predicate"), F.col(name).cast("string").alias("object")))
    edges = export_graph(run).select(F.col("node").alias("subject"), F.col("relation").alias("predicate"), F.col("to").alias("object"))
    return _union([*values, edges])


def sub_run(triples: DataFrame, labels: list[str]) -> DataFrame:
    """The triples of given result elements and of the steps behind them."""
    names = [f"result:{x}" for x in labels]
    own = triples.filter(F.col("subject").isin(names))
    steps = own.filter("predicate = 'generated_by'").select(F.col("object").alias("subject")).distinct()
    return own.unionByName(triples.join(F.broadcast(steps), "subject", "left_semi").select(*own.columns))


def trail(graph: DataFrame, nodes: DataFrame, depth: int) -> DataFrame:
    """``node``: what lies within ``depth`` edges behind given nodes.  A run's graph has depth 2, known from the query."""
    seen = front = nodes.select("node").distinct()
    for _ in range(depth):
        front = graph.join(front, "node").select(F.col("to").alias("node")).distinct()
        seen = seen.unionByName(front)
    return seen.distinct()


# --- redaction ---------------------------------------------------------------------------------------------------------


def redact(s: Slice, sensitive: dict[str, list[str]]) -> tuple[dict[str, Demand], DataFrame]:
    """A slice without listed input columns; and the demanded cells that this hides, ``(source_table, lbl, column)``.

    The result can be recomputed from the redacted slice exactly when no demanded cell is hidden.
    """
    out, hidden = {}, []
    for name, d in s.inputs.items():
        columns = [c for c in sensitive.get(name, []) if c in d.columns]
        for c in columns:
            hidden.append(d.labelled().filter(F.col(mask(c)) > 0).select(F.lit(name).alias("source_table"), "lbl", F.lit(c).alias("column")))
        out[name] = Demand(name, d.rows.withColumns({mask(c): F.lit(0).cast("tinyint") for c in columns}), d.rest, d.columns)
    empty = s.run.cat.spark.createDataFrame([], "source_table string, lbl string, column string")
    return out, _union(hidden) if hidden else empty
