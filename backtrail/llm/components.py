"""Connected components by alternating large and small stars, for graphs of any size.

Every step is an aggregate (which combines before its shuffle) and an equi-join (which adaptive execution splits where a
node has very many edges); no task holds a component.  Each round is checkpointed in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.llm.common import durable


def _large(edges: DataFrame) -> DataFrame:
    both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small(edges: DataFrame) -> DataFrame:
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionAll(least.select("u", F.col("m").alias("v"))).distinct()


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def components(links: DataFrame) -> DataFrame:
    """``(node, root)`` for every node of ``links(u, v)`` (long, not null) but the roots; root = smallest node reachable.

    No links give no rows; repeated links, self-links and either direction are the same graph.
    """
    edges = durable(links.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    mark = _mark(edges)
    while mark[0]:
        edges = durable(_small(_large(edges)))
        before, mark = mark, _mark(edges)
        if before == mark:
            break
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def marked(df: DataFrame) -> DataFrame:
    """``df`` with ``__row``, a hash of all columns that tells rows of one id apart."""
    return df.withColumn("__row", F.xxhash64(*df.columns))


def keep_least(rows: DataFrame, named: DataFrame, joined: DataFrame, id_col: str) -> DataFrame:
    """Of each component one of the ``marked`` rows, and all rows without an id.

    ``named(key struct(id, row), fp)`` has the node of every row, ``joined(node, root)`` the components.  The row of the smallest
    (id, fp, row) is kept; rows of one id in different components all stay.
    """
    classes = named.filter("key.id is not null").join(joined, named["fp"] == joined["node"], "left")
    least = classes.groupBy(F.coalesce("root", "fp").alias("root")).agg(F.min(F.struct("key.id", "fp", "key.row")).alias("least"))
    kept = least.select(F.col("least.id").alias("__id"), F.col("least.row").alias("__least"))
    here = (rows[id_col] == kept["__id"]) & (rows["__row"] == kept["__least"])
    found = rows.join(kept, here, "left_semi").dropDuplicates([id_col, "__row"])
    return found.unionByName(rows.filter(F.col(id_col).isNull())).drop("__row")
