"""Executable forms of the guarantees: each returns its violations, and none is the expected answer."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from backtrail.operators import differences
from backtrail.functions.frames import leq_violations
from backtrail.operators.replay import replay
from backtrail.operators.runs import Run, trace, trace_rows
from backtrail.operators.slicing import SKIP, Demand, Target, fill, mask, slice_inputs, slice_query, sliced_run, value_at, values_at
from backtrail.plans import compile as plan
from backtrail.plans.expr import Const
from backtrail.sources.catalog import Catalog, Edits


def altered(column: str, kind: T.DataType, keys: list[str], seed: int) -> Column:
    """Another value of a column's type, by a hash of seed, label and column; small numbers, so that primitives stay defined."""
    h = F.xxhash64(F.lit(f"{seed} {column}"), *keys)
    if isinstance(kind, T.StringType):
        return F.concat(F.lit("~"), F.hex(h))
    if isinstance(kind, T.BooleanType):
        return h % 2 == 0
    if isinstance(kind, (T.DoubleType, T.FloatType, T.DecimalType)):
        return (F.pmod(h, F.lit(1000)) / 4).cast(kind)
    if isinstance(kind, (T.IntegerType, T.LongType, T.ShortType, T.ByteType)):
        return F.pmod(h, F.lit(100)).cast(kind)
    return F.lit(None).cast(kind)


def perturbed(cat: Catalog, demands: dict[str, Demand], seed: int = 1, strike: tuple[str, str] | None = None) -> Catalog:
    """A catalog that agrees with the demands and differs wherever they allow it.

    Cells not kept get other values; where the rest is skipped, a tenth of the unlisted elements goes and as many copies come under
    new labels.  ``strike`` names a (table, column) whose kept cells are altered too: a control that must do damage.
    """
    out = cat
    for name, df in cat.tables.items():
        keys = cat.labels(name)
        d = demands.get(name)
        kinds = {f.name: f.dataType for f in df.schema}
        if d is None:
            continue
        joined = df.join(d.rows.select(*keys, *[F.col(mask(c)).alias(f"__m_{c}") for c in d.columns], F.lit(True).alias("__listed")), keys, "left")
        kept = lambda c, n=name: (F.coalesce(f"__m_{c}", F.lit(0)) > 0) & F.lit((n, c) != strike)
        cells = [F.when(kept(c), F.col(c)).otherwise(altered(c, kinds[c], keys, seed)).alias(c) for c in d.columns]
        changed = joined.select(*keys, *cells, F.coalesce("__listed", F.lit(False)).alias("__listed"))
        if d.rest == SKIP:
            tenth = F.pmod(F.xxhash64(F.lit(seed), *keys), F.lit(10))
            top = df.agg(F.max(keys[0])).first()[0] or 0  # a number, so that labels asked for are looked up in the table
            stay = changed.filter(F.col("__listed") | (tenth != 0))
            new = changed.filter(~F.col("__listed") & (tenth == 1)).withColumn(keys[0], F.col(keys[0]) + (top + 1))
            changed = stay.unionByName(new)
        out = out.replaced(name, changed.drop("__listed").select(*df.columns))
    return out


def target_violations(run: Run, target: Target, cat: Catalog, expr=None) -> DataFrame:
    """``(lbl, reason)`` where a rerun over another catalog does not agree with the run as far as the target goes."""
    again = Run(run.expr, cat, run.blocks, "on_demand", "taken") if expr is None else trace(expr, cat)
    paired = expr is None and target.rest != SKIP and target.asked is not None and not run.labels and all(map(differences.plain, run.blocks))
    few = target.labels if target.rest == SKIP or paired else None
    other = again.value() if few is None else values_at(again, few)
    out = None
    for i, block in enumerate(run.blocks):
        names = [k for k, _ in block.fields()]
        labels = plan.all_labels(block, run.cat)
        listed = target.asked if paired else target.frames
        own = (run.value_of(i) if few is None else value_at(run, i, few)).join(listed[i].select(*labels, *[F.col(mask(k)).alias(f"__m_{k}") for k in names]), labels)
        both = own.join(other.select("lbl", *[F.col(k).alias(f"__n_{k}") for k in names], F.lit(True).alias("__there")), "lbl", "left")
        wrong = reduce(lambda a, b: a | b, [(F.col(f"__m_{k}") > 0) & ~F.col(k).eqNullSafe(F.col(f"__n_{k}")) for k in names])
        rows = both.select("lbl", F.when(F.col("__there").isNull(), F.lit("missing")).when(wrong, F.lit("changed")).alias("reason")).filter("reason is not null")
        out = rows if out is None else out.unionByName(rows)
    if paired:  # all other elements: their labels alone, which must be the same on both sides
        gone, new = differences.labels(run.blocks, run.cat, cat), differences.labels(run.blocks, cat, run.cat)
        known = out.select("lbl")
        return out.unionByName(gone.join(known, "lbl", "left_anti").withColumn("reason", F.lit("missing"))).unionByName(new.withColumn("reason", F.lit("unlisted")))
    if target.rest != SKIP:
        out = out.unionByName(other.select("lbl").join(run.value().select("lbl"), "lbl", "left_anti").select("lbl", F.lit("unlisted").alias("reason")))
    return out


def slice_violations(run: Run, target: Target, seed: int = 1, strike=None) -> DataFrame:
    """Slice correctness: the target must survive any change outside the input slice."""
    return target_violations(run, target, perturbed(run.cat, slice_inputs(run, target), seed, strike))


def query_slice_violations(run: Run, target: Target, seed: int = 1, chooser=lambda: Const(None)) -> DataFrame:
    """Query-slice correctness: the holes may be filled with anything, and the inputs changed outside the slice."""
    filled = fill(slice_query(run, target), chooser)
    return target_violations(run, target, perturbed(run.cat, slice_inputs(run, target), seed), filled)


def monotone_violations(inner: Target, outer: Target) -> DataFrame:
    """Cells that the smaller target's slice has and the larger one's lacks."""
    small, large = slice_inputs(inner.run, inner), slice_inputs(outer.run, outer)
    return reduce(DataFrame.unionByName, [leq_violations(small[t], large[t]).select(F.lit(t).alias("source_table"), F.lit(1).alias("cell")) for t in small])


def resliced_violations(inner: Target, outer: Target) -> DataFrame:
    """Cells that the inner slice has and the inner slice taken from the outer one has not, or the other way round."""
    cut = sliced_run(outer)
    whole, again = slice_inputs(inner.run, inner), slice_inputs(cut, Target(cut, inner.frames, inner.rest))
    parts = [leq_violations(x[t], y[t]).select(F.lit(t).alias("source_table")) for x, y in ((whole, again), (again, whole)) for t in x]
    return reduce(DataFrame.unionByName, parts)


def consistency_violations(run: Run) -> DataFrame:
    """A trace replayed on its own inputs gives the run's value, and no failure."""
    again = replay(run, run.cat)
    if not run.labels and all(map(differences.plain, run.blocks)):
        differ = differences.rows(run.blocks, run.cat, again.run.cat)
        return differ.select("lbl", F.lit("differs").alias("reason")).unionByName(again.failures.select("lbl", "reason"))
    fields = run.value().columns
    differ = again.value().select(*fields).exceptAll(run.value()).unionByName(run.value().exceptAll(again.value().select(*fields)))
    return differ.select("lbl", F.lit("differs").alias("reason")).unionByName(again.failures.select("lbl", "reason"))


def fidelity(run: Run, edits: Edits) -> tuple[bool, bool]:
    """Whether a replay on edited inputs succeeds; and whether a fresh trace lies within the old one.  The two must be equal."""
    cat = run.cat.apply(edits)
    fresh = trace_rows(trace(run.expr, cat), "full")
    inside = fresh.join(trace_rows(run, "full"), ["site", "lbl", "branch"], "left_anti").limit(1).count() == 0
    known = all(cat[t].select(*cat.labels(t)).join(run.cat[t].select(*cat.labels(t)), cat.labels(t), "left_anti").limit(1).count() == 0 for t in {g.table for b in run.blocks for g in b.gens})
    return replay(run, cat).ok, inside and known


def determinacy_violations(run: Run, partitions: int = 3) -> DataFrame:
    """Rows that change when the inputs are dealt out otherwise."""
    cat = run.cat
    for name in {g.table for b in run.blocks for g in b.gens}:
        cat = cat.replaced(name, cat[name].repartition(partitions, F.xxhash64(F.lit(9), *cat.labels(name))))
    if not run.labels and all(map(differences.plain, run.blocks)):
        return differences.rows(run.blocks, run.cat, cat)
    a, b = run.value(), Run(run.expr, cat, run.blocks, run.mode, run.level).value()
    return a.exceptAll(b).unionByName(b.exceptAll(a))
