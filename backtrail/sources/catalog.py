"""Labelled tables.

Every element of a table has a label: one or more integer columns ``_l0, _l1, …`` that are distinct over the table.  Labels are
attached once, to a snapshot, from the table's keys; edits are expressed against labels and never relabel.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Keys of the given tables.  Lineitem's pair of keys repeats, so an occurrence number in the order of its other columns follows.
KEYS = {
    "region": ["r_regionkey"], "nation": ["n_nationkey"], "customer": ["c_custkey"], "supplier": ["s_suppkey"], "part": ["p_partkey"],
    "orders": ["o_orderkey"], "lineitem": ["l_orderkey", "l_linenumber"], "events": ["event_id"], "documents": ["doc_id"],
    "embeddings": ["vec_id"], "pages": ["page_id"], "benchmark": ["item_id"], "labels": ["doc_id"], "conversations": ["conv_id", "turn"],
}
TIES = {"lineitem": ["l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]}


#: Edited labels up to so many are broadcast to the table they change.
EDITS = 100_000

#: Types of rows given on the driver.
_KINDS = {"long": pa.int64(), "int": pa.int32(), "tinyint": pa.int8(), "string": pa.string(), "boolean": pa.bool_()}


def given(spark: SparkSession, rows: list[tuple], **columns: str) -> DataFrame:
    """A few rows from the driver as a local relation, which is read back without a job."""
    arrays = [pa.array([r[i] for r in rows], _KINDS[kind]) for i, kind in enumerate(columns.values())]
    return spark.createDataFrame(pa.table(arrays, names=list(columns)))


def kept(df: DataFrame, path: str | None = None) -> DataFrame:
    """What ``df`` holds now: written to ``path``, else to the session's checkpoint folder; persisted where neither is given."""
    if path:
        df.write.mode("overwrite").parquet(path)
        return df.sparkSession.read.parquet(path)
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None and (folder := df.sparkSession.conf.get("spark.checkpoint.dir", None)):
        context.setCheckpointDir(folder)
    if context.getCheckpointDir() is not None:
        return df.checkpoint()
    df = df.persist()
    df.count()
    return df


def label_columns(df: DataFrame) -> list[str]:
    return sorted((c for c in df.columns if c.startswith("_l") and c[2:].isdigit()), key=lambda c: int(c[2:]))


def with_labels(df: DataFrame, keys: list[str], ties: list[str] | None = None) -> DataFrame:
    """``df`` with label columns; with ``ties`` also an occurrence number among rows of equal keys, in the order of these columns."""
    out = df
    for i, key in enumerate(keys):
        out = out.withColumn(f"_l{i}", F.col(key).cast("long"))
    if ties:
        out = out.withColumn(f"_l{len(keys)}", F.row_number().over(Window.partitionBy(*keys).orderBy(*ties)).cast("long"))
    return out


def hashed_labels(df: DataFrame) -> DataFrame:
    """For tables without a key: a non-negative hash of the whole row, then an occurrence number among equal rows."""
    row = F.xxhash64(*df.columns).bitwiseAND(F.lit((1 << 63) - 1))
    out = df.withColumn("_l0", row)
    return out.withColumn("_l1", F.row_number().over(Window.partitionBy("_l0", *df.columns).orderBy(F.lit(0))).cast("long"))


def fresh_labels(df: DataFrame) -> DataFrame:
    """Contrast only: labels that differ from run to run, so that nothing can be addressed across runs."""
    return df.withColumn("_l0", F.pmod(F.xxhash64(F.uuid()), F.lit(1 << 62)))


def collapse_multiplicity(df: DataFrame) -> DataFrame:
    """Contrast only: values with their count, in which equal elements can't be told apart."""
    return df.groupBy(*df.columns).agg(F.count("*").alias("multiplicity"))


def dotted(parts: list[Column]) -> Column:
    return F.concat_ws(".", *[p.cast("string") for p in parts])


def label_array(parts: list[Column]) -> Column:
    return F.array(*[p.cast("long") for p in parts])


def concat_labels(a: Column, b: Column) -> Column:
    return F.concat(a, b)


def is_prefix(a: Column, b: Column) -> Column:
    """Whether array label ``a`` begins label ``b``."""
    return (F.size(a) <= F.size(b)) & (F.slice(b, 1, F.size(a)) == a)


def _prefixes(df: DataFrame, label: str) -> DataFrame:
    lengths = F.sequence(F.lit(0), F.size(label) - 1)
    return df.filter(F.size(label) > 0).select(F.explode(F.transform(lengths, lambda n: F.slice(F.col(label), F.lit(1), n))).alias(label))


def prefix_violations(df: DataFrame, label: str = "label") -> DataFrame:
    """Labels that break a prefix code: repeated ones, and proper prefixes of others."""
    labels = df.select(label)
    repeated = labels.groupBy(label).agg(F.count("*").alias("n")).filter("n > 1").select(label, F.lit("repeated").alias("reason"))
    begins = labels.distinct().join(_prefixes(labels, label).distinct(), label, "left_semi").select(label, F.lit("prefix").alias("reason"))
    return repeated.unionByName(begins)


def sub_code_violations(inner: DataFrame, outer: DataFrame, label: str = "label") -> DataFrame:
    """Labels of ``inner`` that extend no label of ``outer``."""
    rest = inner.select(label)
    lengths = [r[0] for r in outer.filter(F.col(label).isNotNull()).select(F.size(label)).distinct().collect()]
    for n in lengths:  # labels of one length at a time: each inner label is looked up by its beginning, nothing is spread
        own = outer.filter(F.size(label) == n).select(F.col(label).alias("__of")).distinct()
        rest = rest.join(own, (F.size(label) >= n) & (F.slice(label, 1, n) == F.col("__of")), "left_anti")
    return rest


def prefix_disjoint_violations(a: DataFrame, b: DataFrame, label: str = "label") -> DataFrame:
    """Labels of either side that equal or begin one of the other side."""

    def hits(x: DataFrame, y: DataFrame) -> DataFrame:
        reach = _prefixes(y.select(label), label).unionByName(y.select(label)).distinct()
        return x.select(label).distinct().join(reach, label, "left_semi")

    return hits(a, b).unionByName(hits(b, a)).distinct()


@dataclass
class Edits:
    """Changes of one table by label: new values, deletions, insertions, dropped and added fields."""

    table: str
    updates: list[tuple[tuple, str, object]] = field(default_factory=list)
    deletes: list[tuple] = field(default_factory=list)
    inserts: list[tuple[tuple, dict]] = field(default_factory=list)
    dropped: list[str] = field(default_factory=list)
    added: dict[str, object] = field(default_factory=dict)

    def update(self, label: tuple, column: str, value) -> Edits:
        self.updates.append((tuple(label), column, value))
        return self

    def delete(self, label: tuple) -> Edits:
        self.deletes.append(tuple(label))
        return self

    def insert(self, label: tuple, **values) -> Edits:
        self.inserts.append((tuple(label), values))
        return self

    def drop_field(self, column: str) -> Edits:
        self.dropped.append(column)
        return self

    def add_field(self, column: str, value) -> Edits:
        self.added[column] = value
        return self


class Catalog:
    """Name to labelled table."""

    def __init__(self, spark: SparkSession, tables: dict[str, DataFrame] | None = None):
        self.spark, self.tables = spark, dict(tables or {})

    @classmethod
    def of_folder(cls, spark: SparkSession, folder: str, names: list[str] | None = None) -> Catalog:
        cat = cls(spark)
        for name in names or KEYS:
            cat.register(name, spark.read.parquet(f"{folder}/{name}.parquet"), KEYS[name], TIES.get(name))
        return cat

    @classmethod
    def of_rows(cls, spark: SparkSession, **tables) -> Catalog:
        """Small tables from ``name=(columns, {label: row})``; for examples and tests."""
        cat = cls(spark)
        for name, (columns, rows) in tables.items():
            depth = len(next(iter(rows)))
            schema = ", ".join([*(f"_l{i} long" for i in range(depth)), *(f"{c} long" for c in columns)])
            cat.tables[name] = spark.createDataFrame([(*label, *row) for label, row in rows.items()], schema)
        return cat

    def register(self, name: str, df: DataFrame, keys: list[str], ties: list[str] | None = None) -> Catalog:
        self.tables[name] = with_labels(df, keys, ties)
        return self

    def __getitem__(self, name: str) -> DataFrame:
        return self.tables[name]

    def labels(self, name: str) -> list[str]:
        return label_columns(self.tables[name])

    def columns(self, name: str) -> list[str]:
        own = set(self.labels(name))
        return [c for c in self.tables[name].columns if c not in own]

    def types(self) -> dict:
        """Fields of each table's elements; for a table with the one column ``value`` that scalar."""
        def base(kind: str) -> str:
            return "number" if kind in ("tinyint", "smallint", "int", "bigint", "float", "double") or kind.startswith("decimal") else kind

        out = {}
        for name, df in self.tables.items():
            columns = self.columns(name)
            fields = {f.name: base(f.dataType.simpleString()) for f in df.schema if f.name in columns}
            out[name] = fields["value"] if columns == ["value"] else fields
        return out

    def snapshot(self, folder: str, name: str, buckets: int | None = None) -> Catalog:
        """Freezes a table's labels: written once, clustered by label, and read again.  Repeated slices then prune by label."""
        keys = self.labels(name)
        df = self.tables[name]
        (df.repartitionByRange(buckets, *keys) if buckets else df.repartitionByRange(*keys)).sortWithinPartitions(*keys).write.mode("overwrite").parquet(f"{folder}/{name}")
        return self.replaced(name, self.spark.read.parquet(f"{folder}/{name}"))

    def replaced(self, name: str, df: DataFrame) -> Catalog:
        return Catalog(self.spark, self.tables | {name: df})

    def spread(self, *names: str) -> Catalog:
        """The catalog with tables dealt out by label: a small file is read by one task, and then so would be all that it is joined to."""
        tasks = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        return Catalog(self.spark, self.tables | {n: self.tables[n].repartition(tasks, *self.labels(n)) for n in names})

    def apply(self, edits: Edits) -> Catalog:
        """The catalog with one table edited; labels of other elements stay as they are."""
        name, df = edits.table, self.tables[edits.table]
        keys, schema = self.labels(name), self.tables[name].schema
        label = ", ".join(f"{k} long" for k in keys)
        few = lambda df: F.broadcast(df) if len(edits.deletes) + len(edits.updates) <= EDITS else df
        if edits.deletes:
            df = df.join(few(self.spark.createDataFrame(edits.deletes, label)), keys, "left_anti")
        for column in dict.fromkeys(c for _, c, _ in edits.updates):
            kind = schema[column].dataType.simpleString()
            last = {at: str(v) if v is not None else None for at, c, v in edits.updates if c == column}
            new = self.spark.createDataFrame([(*at, v) for at, v in last.items()], f"{label}, __new string").withColumn("__hit", F.lit(True))
            found = df.join(few(new), keys, "left")
            df = found.withColumn(column, F.when(F.col("__hit"), F.col("__new").cast(kind)).otherwise(F.col(column))).drop("__new", "__hit")
        if edits.inserts:
            rows = [dict(zip(keys, at)) | values for at, values in edits.inserts]
            texts = [tuple(None if r.get(f.name) is None else str(r[f.name]) for f in schema) for r in rows]
            added = self.spark.createDataFrame(texts, ", ".join(f"`{f.name}` string" for f in schema))
            df = df.unionByName(added.select(*[F.col(f"`{f.name}`").cast(f.dataType).alias(f.name) for f in schema]))
        for column, value in edits.added.items():
            df = df.withColumn(column, F.lit(value))
        return self.replaced(name, df.drop(*edits.dropped))
