"""Helpers shared by the training-data operators."""

from __future__ import annotations

import sys
import tempfile

from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space of the word pattern ``[^\x20\x09-\x0D]+``.
SPACE = " \t\n\x0b\x0c\r"
#: Bound of one Arrow batch, so that memory follows this and not the length of texts.
BATCH_ROWS, BATCH_BYTES = 1000, 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def batches(df: DataFrame, fn, schema: str) -> DataFrame:
    """``mapInArrow`` with bounded batches; ``fn`` travels by value, so executors need no copy of the package.

    The bounds are settings of the session, read when the plan runs: they stay set for it.
    """
    conf = df.sparkSession.conf
    conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    cloudpickle.register_pickle_by_value(sys.modules["backtrail"])
    return df.mapInArrow(fn, schema)


def once(key, build):
    """Kept in a Python worker, which serves many tasks, until it is asked for something else."""
    kept = vars(sys).setdefault("_backtrail_once", {})
    if key not in kept:
        kept.clear()
        kept[key] = build()
    return kept[key]


def let(value, body):
    """Evaluates ``value`` once a row and hands it to ``body``: a projection merged into a lambda would evaluate it per element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words(text):
    """Words ``[^\x20\x09-\x0D]+`` of a column; null and blank texts have none."""
    trimmed = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACE))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, "[ \\t\\n\\x0B\\f\\r]+"))


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where that is unset (tests)."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="checkpoints-"))
    return context.getCheckpointDir()


def remove(spark: SparkSession, folder: str) -> None:
    """Deletes a folder, wherever it is stored."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def durable(df: DataFrame) -> DataFrame:
    """Cuts the lineage in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint()
