"""Readers and writers around the engine."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from backtrail.operators.runs import Run
from backtrail.operators.slicing import Slice

FORMATS = ("parquet", "csv", "json", "orc", "text")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A table by format; text formats take a schema, so that nothing is inferred by an extra pass."""
    if kind not in FORMATS:
        raise ValueError(f"formats are {', '.join(FORMATS)}")
    reader = spark.read.options(**({"header": "true"} | options if kind == "csv" else options))
    return (reader.schema(schema) if schema else reader).format(kind).load(path)


def of_rows(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def numbers(spark: SparkSession, n: int) -> DataFrame:
    """``value`` 1..n with its own label."""
    return spark.range(1, n + 1).select(F.col("id").alias("value"), F.col("id").alias("_l0"))


def write(df: DataFrame, path: str, kind: str = "parquet", by: list[str] | None = None, mode: str = "errorifexists") -> None:
    if kind == "noop":
        df.write.format("noop").mode("overwrite").save()
        return
    writer = df.write.mode(mode).format(kind)
    writer = writer.option("header", "true") if kind == "csv" else writer
    (writer.partitionBy(*by) if by else writer).save(path)


def write_trace(run: Run, name: str, folder: str) -> None:
    """A run's trace frames, partitioned by run and site, so that a slice reads the sites it needs."""
    from backtrail.operators.runs import trace_rows

    trace_rows(run).withColumn("run", F.lit(name)).write.mode("append").partitionBy("run", "site").parquet(folder)


def write_slice(s: Slice, folder: str) -> None:
    """The demanded cells of every table, one folder each."""
    for name, d in s.inputs.items():
        d.cells(s.run.cat).write.mode("overwrite").parquet(f"{folder}/{name}")


def as_views(run: Run, prefix: str, demand: Slice | None = None) -> list[str]:
    """Temporary views of a run for SQL: its value, its trace, and a slice's demands."""
    from backtrail.operators.runs import trace_rows

    # beside each label its numbers, by generator: a view read by them needs no label texts
    parts = [run.value_of(i) for i in range(len(run.blocks))]
    reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts).createOrReplaceTempView(f"{prefix}_value")
    trace_rows(run).createOrReplaceTempView(f"{prefix}_trace")
    names = [f"{prefix}_value", f"{prefix}_trace"]
    for name, d in (demand.inputs.items() if demand else ()):
        d.labelled().createOrReplaceTempView(f"{prefix}_demand_{name}")
        names.append(f"{prefix}_demand_{name}")
    return names
