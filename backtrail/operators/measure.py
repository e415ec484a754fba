"""Costs and precision of the methods."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.operators.checks import altered
from backtrail.operators.runs import Run, static_nodes, trace, trace_nodes
from backtrail.operators.slicing import Target, mask, slice_inputs, slice_nodes, slice_trace, sliced_trace, marks_frame
from backtrail.plans.expr import Expr
from backtrail.sources.catalog import Catalog


def seconds(action: Callable[[], object]) -> float:
    began = time.perf_counter()
    action()
    return time.perf_counter() - began


def consume(df: DataFrame) -> None:
    """Computes every row and column, and keeps none."""
    df.write.format("noop").mode("overwrite").save()


def read_all(df: DataFrame, small: bool) -> None:
    """Computes a result; a small one comes to the driver, as its user would have it."""
    df.collect() if small else consume(df)


def kept_fraction(run: Run, target: Target) -> DataFrame:
    """``(source_table, kept_cells, cells)``: how much of the inputs a slice keeps."""
    out = []
    for name, d in slice_inputs(run, target).items():
        kept = d.rows.agg(*[F.sum((F.col(mask(c)) > 0).cast("int")).alias(c) for c in d.columns]).first()
        out.append((name, sum(v or 0 for v in kept), run.cat[name].count() * len(d.columns)))
    return run.cat.spark.createDataFrame(sorted(out), "source_table string, kept_cells long, cells long")


def nodes(run: Run, target: Target) -> dict[str, int]:
    """Trace nodes: all, in the slice of the target as it is, in that of its closed form."""
    return {"full": trace_nodes(run), "open": slice_nodes(slice_trace(run, target)), "closed": slice_nodes(slice_trace(run, target.closed()))}


def growth(expr_of: Callable[[Catalog], Expr], catalogs: list[tuple[int, Catalog]]) -> list[dict]:
    """Trace nodes as trees and with sharing for inputs of growing size, and the slope between neighbours in log-log scale."""
    rows: list[dict] = []
    for n, cat in catalogs:
        run = trace(expr_of(cat), cat)
        row = {"n": n, "tree": trace_nodes(run), "shared": static_nodes(run.expr)}
        if rows:
            row["slope"] = math.log(row["tree"] / rows[-1]["tree"]) / math.log(n / rows[-1]["n"])
        rows.append(row)
    return rows


def grid(expr: Expr, cat: Catalog, target_of: Callable[[Run], Target], stored_of: Callable[[Run], Target] | None = None, folder: str | None = None, level: str = "full") -> list[dict]:
    """The experiment: every mode with simple (closed) and enriched (open) patterns; seconds of each step.

    Eager and lazy runs trace at the same level, so their steps do the same work.  ``stored_of`` gives the enriched target as rows, whose
    slice reads the recorded trace; it is reported as a pattern of its own beside that of a few labels given on the driver.
    """
    out = []
    base = seconds(lambda: consume(trace(expr, cat).value()))
    kinds = {"simple": lambda run: target_of(run).closed(), "enriched": target_of} | ({"enriched, recorded": stored_of} if stored_of else {})
    for mode in ("eager", "lazy", "on_demand"):
        for kind, made in kinds.items():
            runs: list[Run] = []

            def traced_run(mode=mode, runs=runs) -> None:
                run = trace(expr, cat, mode, level, folder)
                runs.append(run)

            traced = seconds(traced_run)
            run = runs[0]
            target = made(run)
            few = target.local is not None
            cut = seconds(lambda r=run, t=target, f=few: [*(read_all(d.rows, f) for d in slice_inputs(r, t).values()), read_all(sliced_trace(slice_trace(r, t)), f)])
            query = seconds(lambda r=run, t=target: read_all(marks_frame(r, t), True))
            out.append({"mode": mode, "pattern": kind, "eval": base, "trace": traced, "slice": cut, "qslice": query})
    return out


def stored_bytes(run: Run, folder: str) -> int:
    """Bytes that a stored trace takes; 0 on demand, where nothing is stored."""
    if run.mode == "on_demand":
        return 0
    spark = run.cat.spark
    for (i, k), df in run.frames.items():
        df.write.mode("overwrite").parquet(f"{folder}/block={i}/step={k}")
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    return path.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(path).getLength()


def probe_precision(run: Run, target: Target, limit: int | None = None) -> dict[str, int]:
    """Of the kept cells, how many change the target when each alone is altered.  One rerun per cell: for small inputs only.

    ``limit`` bounds the elements probed per table; ``kept`` counts all kept cells, ``probed`` those that were altered.
    """
    from backtrail.operators.checks import target_violations

    hit = probed = kept = 0
    for name, d in slice_inputs(run, target).items():
        keys = run.cat.labels(name)
        kinds = {f.name: f.dataType for f in run.cat[name].schema}
        sums = d.rows.agg(*[F.sum((F.col(mask(c)) > 0).cast("int")).alias(c) for c in d.columns]).first()
        kept += sum(v or 0 for v in sums)
        ordered = d.rows.orderBy(*keys)
        for row in (ordered if limit is None else ordered.limit(limit)).collect():
            for c in d.columns:
                if row[mask(c)]:
                    here = F.lit(True)
                    for k in keys:
                        here = here & (F.col(k) == row[k])
                    changed = run.cat[name].withColumn(c, F.when(here, altered(c, kinds[c], keys, 3)).otherwise(F.col(c)))
                    probed += 1
                    hit += target_violations(run, target, run.cat.replaced(name, changed)).limit(1).count()
    return {"changing": hit, "probed": probed, "kept": kept}
