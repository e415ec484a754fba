"""Registered queries of the engine, each with the SQL that checks it where SQL can say it.

Conventions: labels are dotted strings, masks and levels integers, money whole cents; demands come as cells
``(source_table, lbl, column)``.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from backtrail import workloads as w
from backtrail.functions import frames
from backtrail.operators import checks, joins, measure, provenance
from backtrail.operators.replay import can_replay, inside_demand, recompute, replay, replay_slice
from backtrail.operators.runs import branch_counts, evaluate, measured_depth, reached, trace, trace_nodes, trace_rows
from backtrail.operators.slicing import CLOSED, SAME, SKIP, Demand, Target, diff_inputs, diff_query, diff_trace, first_labels, leq, marks_frame, melted, slice_inputs, slice_trace, sliced_trace
from backtrail.plans import compile as plan
from backtrail.sources.catalog import Catalog, Edits, collapse_multiplicity, dotted, hashed_labels, label_array, prefix_disjoint_violations, prefix_violations, sub_code_violations

QUERIES: dict = {}
SQL: dict[str, str] = {}

# --- SQL fragments -----------------------------------------------------------------------------------------------------

LINES = (
    "SELECT *, concat_ws('.', l_orderkey, l_linenumber, row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY l_partkey, l_suppkey, "
    "l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate)) AS lbl FROM lineitem"
)


def registered(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return add


def cells(inputs: dict[str, Demand]) -> DataFrame:
    """Demands as ``(source_table, lbl, column)``."""
    return reduce(DataFrame.unionByName, [melted(d).select(F.lit(t).alias("source_table"), "lbl", "column") for t, d in inputs.items()])


def cell_sql(*parts: tuple[str, str, list[str]]) -> str:
    """Cells of ``(table, SQL of lbl, columns)``."""
    return " UNION ".join(f"SELECT '{t}' AS source_table, lbl, '{c}' AS \"column\" FROM ({sql}) t" for t, sql, columns in parts for c in columns)


def key_sql(table: str, key: str, where: str = "true") -> str:
    return f"SELECT CAST({key} AS VARCHAR) AS lbl FROM {table} WHERE {where}"


def counted(spark: SparkSession, frames_: dict[str, DataFrame]) -> DataFrame:
    """``(name, violations)``."""
    return reduce(DataFrame.unionByName, [df.agg(F.count("*").alias("violations")).select(F.lit(k).alias("name"), "violations") for k, df in frames_.items()])


def zero_sql(*names: str) -> str:
    return " UNION ALL ".join(f"SELECT '{n}' AS name, CAST(0 AS BIGINT) AS violations" for n in names)


# --- labels ------------------------------------------------------------------------------------------------------------


@registered("label_lineitem", f"SELECT lbl, l_partkey FROM ({LINES}) t")
def _(spark, d):
    df = w.catalog(spark, d, "lineitem")["lineitem"]
    return df.select(dotted([F.col("_l0"), F.col("_l1"), F.col("_l2")]).alias("lbl"), "l_partkey")


@registered("label_prefix_violations", "SELECT concat_ws('.', l_orderkey, l_linenumber) AS lbl, 'repeated' AS reason FROM lineitem GROUP BY l_orderkey, l_linenumber HAVING count(*) > 1")
def _(spark, d):
    """Without its occurrence number lineitem's label repeats; the full label breaks nothing."""
    df = w.catalog(spark, d, "lineitem")["lineitem"]
    short = prefix_violations(df.select(label_array([F.col("_l0"), F.col("_l1")]).alias("label")))
    full = prefix_violations(df.select(label_array([F.col("_l0"), F.col("_l1"), F.col("_l2")]).alias("label")))
    return short.unionByName(full).select(F.array_join("label", ".").alias("lbl"), "reason")


@registered("label_union", f"SELECT concat(CASE WHEN l_discount < l_tax THEN '1.' ELSE '2.' END, lbl) AS lbl FROM ({LINES}) t")
def _(spark, d):
    return evaluate(w.swap(), w.catalog(spark, d, "lineitem")).select("lbl")


@registered("label_join", "SELECT concat_ws('.', c_custkey, s_suppkey) AS lbl FROM customer JOIN supplier ON c_nationkey = s_nationkey")
def _(spark, d):
    return evaluate(w.join(), w.catalog(spark, d, "customer", "supplier")).select("lbl")


@registered("label_sub_code", zero_sql("iterations within results", "branches disjoint"))
def _(spark, d):
    """Labels of a join's iterations lie within its source's; labels of a union's branches are disjoint."""
    cat = w.catalog(spark, d, "customer", "supplier")
    run = trace(w.join(), cat)
    found = run.result_labels(0).select(F.array(*[F.col(c).cast("string") for c in plan.all_labels(run.blocks[0], cat)]).alias("label"))
    source = cat["customer"].select(F.array(F.col("_l0").cast("string")).alias("label"))
    one, two = (source.select(F.concat(F.array(F.lit(n)), "label").alias("label")) for n in ("1", "2"))
    return counted(spark, {"iterations within results": sub_code_violations(found, source), "branches disjoint": prefix_disjoint_violations(one, two)})


@registered("label_multiplicity", "SELECT p_size, count(*) AS multiplicity FROM part GROUP BY p_size")
def _(spark, d):
    return collapse_multiplicity(spark.read.parquet(f"{d}/part.parquet").select("p_size"))


@registered("label_hashed", "SELECT r_name, CAST(row_number() OVER (PARTITION BY r_name ORDER BY 1) AS BIGINT) AS occurrence FROM (SELECT r_name FROM region UNION ALL SELECT r_name FROM region) t")
def _(spark, d):
    names = spark.read.parquet(f"{d}/region.parquet").select("r_name")
    return hashed_labels(names.unionAll(names)).select("r_name", F.col("_l1").alias("occurrence"))


# --- evaluation --------------------------------------------------------------------------------------------------------


@registered("eval_swap", f"SELECT concat(CASE WHEN l_discount < l_tax THEN '1.' ELSE '2.' END, lbl) AS lbl, least(l_discount, l_tax) AS \"A\", greatest(l_discount, l_tax) AS \"B\", l_quantity AS \"C\" FROM ({LINES}) t")
def _(spark, d):
    return evaluate(w.swap(), w.catalog(spark, d, "lineitem"))


@registered("eval_select", f"SELECT lbl, l_partkey AS \"A\", l_extendedprice AS \"B\" FROM ({LINES}) t WHERE l_quantity = 3")
def _(spark, d):
    return evaluate(w.selection(), w.catalog(spark, d, "lineitem"))


@registered("eval_rename", f"SELECT lbl, least(l_discount, l_tax) AS \"A\", greatest(l_discount, l_tax) AS \"B\", l_quantity AS \"C\" FROM ({LINES}) t")
def _(spark, d):
    return evaluate(w.renaming(), w.catalog(spark, d, "lineitem"))


@registered("eval_rename_fields", "SELECT CAST(p_partkey AS VARCHAR) AS lbl, p_size AS size FROM part")
def _(spark, d):
    return evaluate(w.part_sizes(), w.catalog(spark, d, "part"))


@registered("eval_union_const", "SELECT concat('1.', p_partkey) AS lbl, p_size AS \"B\" FROM part UNION ALL SELECT '2', 3")
def _(spark, d):
    return evaluate(w.projection_and_constant(), w.catalog(spark, d, "part"))


@registered("eval_join", "SELECT concat_ws('.', c_custkey, s_suppkey) AS lbl, c_acctbal AS \"A\", s_name AS \"B\" FROM customer JOIN supplier ON c_nationkey = s_nationkey")
def _(spark, d):
    return evaluate(w.join(), w.catalog(spark, d, "customer", "supplier").spread("customer"))


@registered("eval_join_large", f"SELECT concat_ws('.', lbl, o_orderkey) AS lbl, l_partkey AS \"A\", o_orderpriority AS \"B\" FROM ({LINES}) t JOIN orders ON l_orderkey = o_orderkey")
def _(spark, d):
    return evaluate(w.large_join(), w.catalog(spark, d, "lineitem", "orders"))


_TRIPLES = "(SELECT p_partkey AS v FROM part WHERE p_partkey BETWEEN 1 AND 50)"
_WORKFLOW = f"FROM {_TRIPLES} a JOIN {_TRIPLES} b ON a.v < b.v JOIN {_TRIPLES} c ON a.v * a.v + b.v * b.v = c.v * c.v"


@registered("eval_workflow", f"SELECT concat_ws('.', a.v, b.v, c.v) AS lbl, a.v * b.v AS value {_WORKFLOW}")
def _(spark, d):
    return evaluate(w.workflow(), w.workflow_catalog(spark, d))


_COPIES = "FROM documents a JOIN documents b ON a.text = b.text AND a.doc_id < b.doc_id JOIN labels l ON l.doc_id = a.doc_id AND l.quality = 1"


@registered("eval_docs", f"SELECT concat_ws('.', a.doc_id, b.doc_id, l.doc_id) AS lbl, a.n_chars + b.n_chars AS n {_COPIES}")
def _(spark, d):
    return evaluate(w.document_copies(), w.catalog(spark, d, "documents", "labels"))


@registered("eval_sum", "SELECT '0' AS lbl, CAST(coalesce(sum(CAST(round(l_extendedprice * 100) AS BIGINT)), 0) AS BIGINT) AS total FROM lineitem WHERE l_quantity = 3")
def _(spark, d):
    return evaluate(w.total(), w.one_catalog(spark, d, "lineitem"))


_NO_F = "NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')"


@registered("eval_empty", f"SELECT CAST(c_custkey AS VARCHAR) AS lbl, c_name AS \"A\" FROM customer WHERE {_NO_F}")
def _(spark, d):
    return evaluate(w.without_orders(), w.catalog(spark, d, "customer", "orders"))


@registered("eval_intersect", "SELECT CAST(c_custkey AS VARCHAR) AS lbl, c_name AS \"A\" FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def _(spark, d):
    from backtrail.plans.expr import intersect, table

    q = intersect(table("customer"), table("orders"), lambda a, b: w.f(a, "c_custkey").eq(w.f(b, "o_custkey")) & w.f(b, "o_orderstatus").eq("F"), lambda a: w.rec(A=w.f(a, "c_name")))
    return evaluate(q, w.catalog(spark, d, "customer", "orders"))


@registered("eval_group", "SELECT CAST(n_nationkey AS VARCHAR) AS lbl, n_name AS name, count(c_custkey) AS n, CAST(coalesce(sum(CAST(round(c_acctbal * 100) AS BIGINT)), 0) AS BIGINT) AS cents FROM nation LEFT JOIN customer ON n_nationkey = c_nationkey GROUP BY n_nationkey, n_name")
def _(spark, d):
    return evaluate(w.customers_by_nation(), w.catalog(spark, d, "nation", "customer"))


@registered("eval_let", f"SELECT concat_ws('.', lbl, o_orderkey) AS lbl, l_partkey AS p, o_orderstatus AS s FROM ({LINES}) t JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity > 49")
def _(spark, d):
    return evaluate(w.big_lines(), w.catalog(spark, d, "lineitem", "orders"))


_NESTED = f"SELECT concat_ws('.', c_custkey, o_orderkey, lbl) AS lbl, concat_ws('.', c_custkey, o_orderkey, l_linenumber, split_part(lbl, '.', 3)) AS short, c_name AS name, o_orderstatus AS status, l_quantity AS quantity FROM customer JOIN orders ON o_custkey = c_custkey JOIN ({LINES}) t ON l_orderkey = o_orderkey"


@registered("eval_nested", f"SELECT lbl, name, status, quantity FROM ({_NESTED}) n")
def _(spark, d):
    return evaluate(w.nested_lines(), w.catalog(spark, d, "customer", "orders", "lineitem"))


@registered("eval_nested_bags", f"SELECT short AS lbl, name, status, quantity FROM ({_NESTED}) n")
def _(spark, d):
    return w.unnested(w.nested_frame(w.catalog(spark, d, "customer", "orders", "lineitem")))


_SWEEP = "SELECT i, k, lim, kind, (SELECT count(*) FROM events WHERE event_type = kind AND value > lim) AS n FROM (VALUES (0, 50), (1, 100), (2, 200), (3, 400)) a(i, lim), (VALUES (0, 'purchase'), (1, 'click'), (2, 'view'), (3, 'signup'), (4, 'logout')) b(k, kind)"


@registered("eval_sweep", f"SELECT concat_ws('.', i, k) AS lbl, CAST(lim AS BIGINT) AS \"limit\", kind AS event_type, n FROM ({_SWEEP}) s")
def _(spark, d):
    return evaluate(w.sweep(), w.with_above(w.sweep_catalog(spark, d)))


@registered("eval_vectors", "SELECT concat_ws('.', a.vec_id, b.vec_id) AS lbl, a.label AS label FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id < b.vec_id WHERE list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: CAST(p[1] AS DOUBLE) * CAST(p[2] AS DOUBLE))) > 0.25")
def _(spark, d):
    return evaluate(w.near_vectors(), w.catalog(spark, d, "embeddings"))


@registered("eval_vectors_udf", SQL["eval_vectors"])
def _(spark, d):
    """The same opaque step as an Arrow-batched Python function."""
    from backtrail.functions.udfs import dot_product
    from backtrail.plans.expr import primitive

    return evaluate(w.near_vectors(product=primitive("dot", dot_product(), "number")), w.catalog(spark, d, "embeddings"))


_HOST = "regexp_extract({}.url, '^https?://([^/]+)', 1)"
_TITLE = "length(regexp_extract({}.html, '<title>([^<]*)</title>', 1))"


@registered("eval_pages", f"SELECT concat_ws('.', a.page_id, b.page_id) AS lbl, {_HOST.format('a')} AS host, CAST({_TITLE.format('a')} + {_TITLE.format('b')} AS INTEGER) AS n FROM pages a JOIN pages b ON {_HOST.format('a')} = {_HOST.format('b')} AND a.page_id < b.page_id")
def _(spark, d):
    return evaluate(w.pages_of_a_host(), w.catalog(spark, d, "pages"))


@registered("eval_contamination", "SELECT concat_ws('.', doc_id, item_id) AS lbl, n_chars FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def _(spark, d):
    docs = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "text", "n_chars")
    items = spark.read.parquet(f"{d}/benchmark.parquet").select("item_id", F.col("text").alias("item"))
    return joins.contains_join(docs, items, "text", "item").select(F.concat_ws(".", F.col("doc_id").cast("string"), F.col("item_id").cast("string")).alias("lbl"), "n_chars")


# --- traces ------------------------------------------------------------------------------------------------------------


@registered("trace_select", f"SELECT 3 AS site, lbl, l_quantity = 3 AS branch FROM ({LINES}) t")
def _(spark, d):
    return trace_rows(trace(w.selection(), w.catalog(spark, d, "lineitem"), "lazy", "full"))


@registered("trace_join_taken", "SELECT 5 AS site, concat_ws('.', c_custkey, s_suppkey) AS lbl, true AS branch FROM customer JOIN supplier ON c_nationkey = s_nationkey")
def _(spark, d):
    return trace_rows(trace(w.join(), w.catalog(spark, d, "customer", "supplier"), "lazy", "taken"))


@registered("trace_join_full", "SELECT c_nationkey = s_nationkey AS branch, count(*) AS n FROM customer, supplier GROUP BY 1")
def _(spark, d):
    """Branches of all pairs, failing ones too: from counts, whatever the number of pairs."""
    return branch_counts(trace(w.join(), w.catalog(spark, d, "customer", "supplier"))).select("branch", "n")


@registered("trace_workflow_counts", f"SELECT 7 AS site, (a.v < b.v AND a.v * a.v + b.v * b.v = c.v * c.v) AS branch, count(*) AS n FROM {_TRIPLES} a, {_TRIPLES} b, {_TRIPLES} c GROUP BY 2")
def _(spark, d):
    return trace_rows(trace(w.workflow(), w.workflow_catalog(spark, d), "lazy", "full")).groupBy("site", "branch").agg(F.count("*").alias("n"))


_NODES = (
    "SELECT 'select' AS name, 2 + 6 * count(*) + 5 * count(*) FILTER (l_quantity = 3) AS nodes FROM lineitem"
    " UNION ALL SELECT 'join', 2 + 2 * (SELECT count(*) FROM customer) + 7 * (SELECT count(*) FROM customer) * (SELECT count(*) FROM supplier) + 5 * count(*) FROM customer JOIN supplier ON c_nationkey = s_nationkey"
    " UNION ALL SELECT 'union_const', 6 + 4 * count(*) FROM part"
    f" UNION ALL SELECT 'workflow', 2 + 2 * n + 2 * n * n + 17 * n * n * n + 3 * (SELECT count(*) {_WORKFLOW}) FROM (SELECT count(*) AS n FROM {_TRIPLES} t) s"
)


@registered("trace_nodes", _NODES)
def _(spark, d):
    cat = w.catalog(spark, d, "lineitem", "customer", "supplier", "part")
    runs = {"select": (w.selection(), cat), "join": (w.join(), cat), "union_const": (w.projection_and_constant(), cat), "workflow": (w.workflow(), w.workflow_catalog(spark, d))}
    return spark.createDataFrame([(k, trace_nodes(trace(*v))) for k, v in runs.items()], "name string, nodes long")


# --- slices ------------------------------------------------------------------------------------------------------------


def _first(run, fields=None, by="lbl", n=1) -> Target:
    labels = first_labels(run, n) if by == "lbl" else [r[0] for r in run.value().orderBy(by).limit(n).select("lbl").collect()]
    return Target.cells(run, {lbl: fields if fields is not None else [k for b in run.blocks for k, _ in b.fields()] for lbl in labels})


_FIRST_LINE = f"SELECT lbl FROM ({LINES}) t WHERE l_quantity = 3 ORDER BY lbl LIMIT 1"


def select_slice(spark: SparkSession, d: str) -> DataFrame:
    """The input cells behind the price of the selection's first result element."""
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return cells(slice_inputs(run, _first(run, ["B"])))


registered("slice_select_enriched", cell_sql(("lineitem", _FIRST_LINE, ["l_quantity", "l_extendedprice"])))(select_slice)


@registered("slice_select_simple", cell_sql(("lineitem", LINES, ["l_quantity"]), ("lineitem", _FIRST_LINE, ["l_extendedprice"])))
def _(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return cells(slice_inputs(run, _first(run, ["B"]).closed()))


@registered("slice_select_same", cell_sql(("lineitem", LINES, ["l_quantity"]), ("lineitem", f"{LINES} WHERE l_quantity = 3", ["l_partkey", "l_extendedprice"])).replace("FROM lineitem WHERE l_quantity = 3", "FROM lineitem QUALIFY l_quantity = 3"))
def _(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return cells(slice_inputs(run, _first(run, ["B"]).same()))


@registered("slice_swap_enriched", cell_sql(("lineitem", f"SELECT lbl FROM ({LINES}) t WHERE l_orderkey = 0 AND l_linenumber IN (2, 4)", ["l_discount", "l_tax"])))
def _(spark, d):
    """One field of every element of order 0, lines 2 and 4, whichever branch they took: the condition's columns."""
    run = trace(w.swap(), w.catalog(spark, d, "lineitem"))
    return cells(slice_inputs(run, Target.where(run, F.col("lbl").rlike(r"^[12]\.0\.[24]\."), ["B"])))


@registered("slice_rename_enriched", cell_sql(("lineitem", f"SELECT lbl FROM ({LINES}) t WHERE l_orderkey = 0", ["l_discount", "l_tax"])))
def _(spark, d):
    run = trace(w.renaming(), w.catalog(spark, d, "lineitem"))
    return cells(slice_inputs(run, Target.where(run, F.col("lbl").startswith("0."), ["A"])))


@registered("slice_union_left", cell_sql(("part", key_sql("part", "min(p_partkey)", "p_size = 3"), ["p_size"])))
def _(spark, d):
    run = trace(w.projection_and_constant(), w.catalog(spark, d, "part"))
    first = run.cat["part"].filter("p_size = 3").agg(F.min("p_partkey")).first()[0]
    return cells(slice_inputs(run, Target.cells(run, {f"1.{first}": ["B"]})))


@registered("slice_union_const", "SELECT '' AS source_table, '' AS lbl, '' AS \"column\" WHERE false")
def _(spark, d):
    """The constant rests on no input at all."""
    run = trace(w.projection_and_constant(), w.catalog(spark, d, "part"))
    return cells(slice_inputs(run, Target.cells(run, {"2": ["B"]})))


_PAIRS = "SELECT c_custkey, s_suppkey, row_number() OVER (ORDER BY c_custkey, s_suppkey) AS r FROM customer JOIN supplier ON c_nationkey = s_nationkey"


def _join_target(run) -> Target:
    """The first pair's account, and the second pair's name."""
    ordered = first_labels(run, 2, by_number=True)
    return Target.cells(run, {ordered[0]: ["A"], ordered[1]: ["B"]})


@registered("slice_join_enriched", cell_sql(
    ("customer", f"SELECT CAST(c_custkey AS VARCHAR) AS lbl FROM ({_PAIRS}) p WHERE r <= 2", ["c_nationkey"]), ("customer", f"SELECT CAST(c_custkey AS VARCHAR) AS lbl FROM ({_PAIRS}) p WHERE r = 1", ["c_acctbal"]),
    ("supplier", f"SELECT CAST(s_suppkey AS VARCHAR) AS lbl FROM ({_PAIRS}) p WHERE r <= 2", ["s_nationkey"]), ("supplier", f"SELECT CAST(s_suppkey AS VARCHAR) AS lbl FROM ({_PAIRS}) p WHERE r = 2", ["s_name"]),
))
def _(spark, d):
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    return cells(slice_inputs(run, _join_target(run)))


@registered("slice_join_simple", cell_sql(
    ("customer", key_sql("customer", "c_custkey"), ["c_nationkey"]), ("customer", f"SELECT CAST(c_custkey AS VARCHAR) AS lbl FROM ({_PAIRS}) p WHERE r = 1", ["c_acctbal"]),
    ("supplier", key_sql("supplier", "s_suppkey"), ["s_nationkey"]), ("supplier", f"SELECT CAST(s_suppkey AS VARCHAR) AS lbl FROM ({_PAIRS}) p WHERE r = 2", ["s_name"]),
))
def _(spark, d):
    """Every key of both sides, found without the product of the two."""
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    return cells(slice_inputs(run, _join_target(run).closed()))


@registered("slice_join_large", cell_sql(("lineitem", f"SELECT lbl FROM ({LINES}) t WHERE l_orderkey = 7", ["l_orderkey"]), ("orders", key_sql("orders", "o_orderkey", "o_orderkey = 7 AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = 7)"), ["o_orderkey", "o_orderpriority"])))
def _(spark, d):
    run = trace(w.large_join(), w.catalog(spark, d, "lineitem", "orders"))
    return cells(slice_inputs(run, Target.where(run, F.col("lbl").startswith("7."), ["B"])))


@registered("slice_workflow_enriched", cell_sql(("T", key_sql("(VALUES (3), (4)) v(k)", "k"), ["value"]), ("U", key_sql("(VALUES (5)) v(k)", "k"), ["value"])))
def _(spark, d):
    run = trace(w.workflow(), w.workflow_catalog(spark, d))
    return cells(slice_inputs(run, Target.cells(run, {"3.4.5": ["value"]})))


@registered("slice_workflow_simple", cell_sql(("T", f"SELECT CAST(v AS VARCHAR) AS lbl FROM {_TRIPLES} t", ["value"]), ("U", f"SELECT CAST(v AS VARCHAR) AS lbl FROM {_TRIPLES} t", ["value"])))
def _(spark, d):
    run = trace(w.workflow(), w.workflow_catalog(spark, d))
    return cells(slice_inputs(run, Target.cells(run, {"3.4.5": ["value"]}).closed()))


_COPY = f"SELECT a.doc_id AS i, b.doc_id AS j {_COPIES} ORDER BY i, j LIMIT 1"


@registered("slice_docs_enriched", cell_sql(
    ("documents", f"SELECT CAST(unnest([i, j]) AS VARCHAR) AS lbl FROM ({_COPY}) c", ["doc_id", "text", "n_chars"]), ("labels", f"SELECT CAST(i AS VARCHAR) AS lbl FROM ({_COPY}) c", ["doc_id", "quality"]),
))
def _(spark, d):
    run = trace(w.document_copies(), w.catalog(spark, d, "documents", "labels"))
    first = run.value().orderBy(F.split("lbl", r"\.").cast("array<int>")).select("lbl").first()
    return cells(slice_inputs(run, Target.cells(run, {first[0]: ["n"]} if first else {})))


@registered("slice_sum", cell_sql(("lineitem", LINES, ["l_quantity"]), ("lineitem", f"SELECT lbl FROM ({LINES}) t WHERE l_quantity = 3", ["l_extendedprice"])))
def _(spark, d):
    run = trace(w.total(), w.one_catalog(spark, d, "lineitem"))
    return cells(slice_inputs(run, Target.where(run, F.lit(True), ["total"]))).filter("source_table <> 'one'")


_LONE = f"SELECT min(c_custkey) FROM customer WHERE {_NO_F}"


@registered("slice_empty", cell_sql(("customer", key_sql("customer", "c_custkey", f"c_custkey = ({_LONE})"), ["c_custkey", "c_name"]), ("orders", key_sql("orders", "o_orderkey", f"({_LONE}) IS NOT NULL"), ["o_custkey", "o_orderstatus"])))
def _(spark, d):
    run = trace(w.without_orders(), w.catalog(spark, d, "customer", "orders"))
    first = run.value().agg(F.min(F.col("lbl").cast("long")).cast("string")).first()[0]
    return cells(slice_inputs(run, Target.cells(run, {first: ["A"]})))


def _holders(spark, d):
    from backtrail.plans.expr import intersect, table

    q = intersect(table("customer"), table("orders"), lambda a, b: w.f(a, "c_custkey").eq(w.f(b, "o_custkey")) & w.f(b, "o_orderstatus").eq("F"), lambda a: w.rec(A=w.f(a, "c_name")))
    run = trace(q, w.catalog(spark, d, "customer", "orders"))
    return run, Target.where(run, F.col("lbl").cast("long") < 10, ["A"])


_HOLDERS = "c_custkey < 10 AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')"


@registered("slice_empty_tight", cell_sql(("customer", key_sql("customer", "c_custkey", _HOLDERS), ["c_custkey", "c_name"]), ("orders", f"SELECT CAST(min(o_orderkey) AS VARCHAR) AS lbl FROM orders WHERE o_orderstatus = 'F' AND o_custkey IN (SELECT c_custkey FROM customer WHERE {_HOLDERS}) GROUP BY o_custkey", ["o_custkey", "o_orderstatus"])))
def _(spark, d):
    """Bags that must only not be empty rest on one witness each."""
    run, target = _holders(spark, d)
    return cells(slice_inputs(run, target, tight=True))


@registered("slice_nonempty_exact", cell_sql(("customer", key_sql("customer", "c_custkey", _HOLDERS), ["c_custkey", "c_name"]), ("orders", key_sql("orders", "o_orderkey", f"EXISTS (SELECT 1 FROM customer WHERE {_HOLDERS})"), ["o_custkey", "o_orderstatus"])))
def _(spark, d):
    run, target = _holders(spark, d)
    return cells(slice_inputs(run, target))


@registered("slice_group", cell_sql(("nation", key_sql("nation", "n_nationkey", "n_nationkey = 2"), ["n_nationkey"]), ("customer", key_sql("customer", "c_custkey"), ["c_nationkey"]), ("customer", key_sql("customer", "c_custkey", "c_nationkey = 2"), ["c_acctbal"])))
def _(spark, d):
    run = trace(w.customers_by_nation(), w.catalog(spark, d, "nation", "customer"))
    return cells(slice_inputs(run, Target.cells(run, {"2": ["cents"]})))


@registered("slice_let", cell_sql(("lineitem", f"SELECT lbl FROM ({LINES}) t WHERE l_quantity > 49 AND l_orderkey < 50", ["l_quantity", "l_orderkey", "l_partkey"]), ("orders", key_sql("orders", "o_orderkey", "o_orderkey < 50 AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 49)"), ["o_orderkey"])))
def _(spark, d):
    run = trace(w.big_lines(), w.catalog(spark, d, "lineitem", "orders"))
    return cells(slice_inputs(run, Target.where(run, F.split("lbl", r"\.")[0].cast("long") < 50, ["p"])))


_NEST = f"SELECT * FROM ({LINES}) t JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE c_custkey < 3"


@registered("slice_nested", cell_sql(("customer", f"SELECT CAST(c_custkey AS VARCHAR) AS lbl FROM ({_NEST}) n", ["c_custkey"]), ("orders", f"SELECT CAST(o_orderkey AS VARCHAR) AS lbl FROM ({_NEST}) n", ["o_custkey", "o_orderkey"]), ("lineitem", f"SELECT lbl FROM ({_NEST}) n", ["l_orderkey", "l_quantity"])))
def _(spark, d):
    run = trace(w.nested_lines(), w.catalog(spark, d, "customer", "orders", "lineitem"))
    return cells(slice_inputs(run, Target.where(run, F.split("lbl", r"\.")[0].cast("long") < 3, ["quantity"])))


@registered("slice_sweep_top", cell_sql(("threshold", f"SELECT CAST(i AS VARCHAR) AS lbl FROM ({_SWEEP} ORDER BY n DESC, concat_ws('.', i, k) LIMIT 1) s", ["limit"]), ("kind", f"SELECT CAST(k AS VARCHAR) AS lbl FROM ({_SWEEP} ORDER BY n DESC, concat_ws('.', i, k) LIMIT 1) s", ["event_type"])))
def _(spark, d):
    """The largest count of the sweep: which threshold and type it belongs to."""
    run = trace(w.sweep(), w.with_above(w.sweep_catalog(spark, d)))
    return cells(slice_inputs(run, Target.topk(run, 1, "n", ["n", "limit", "event_type"]))).filter("source_table <> 'above'")


@registered("slice_trace_join", f"SELECT 5 AS site, concat_ws('.', c_custkey, s_suppkey) AS lbl, true AS branch FROM ({_PAIRS}) p WHERE r <= 2")
def _(spark, d):
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    return sliced_trace(slice_trace(run, _join_target(run)))


@registered("slice_cells_select", f"SELECT lbl, l_quantity, l_extendedprice FROM ({LINES}) t WHERE l_quantity = 3 ORDER BY lbl LIMIT 1")
def _(spark, d):
    """The input slice itself: kept values, others null."""
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return slice_inputs(run, _first(run, ["B"]))["lineitem"].cells(run.cat).select(dotted([F.col("_l0"), F.col("_l1"), F.col("_l2")]).alias("lbl"), "l_quantity", "l_extendedprice")


# --- query slices and differences --------------------------------------------------------------------------------------

#: Sites of the selection: comprehension, source, conditional, equality, field, variable, constant, singleton, record, A, B, empty bag.
#: The head's variable is the condition's, so it has no sites of its own.
SELECTION_SITES = 12


def _marks_sql(total: int, **marks: tuple) -> str:
    rows = ", ".join(f"({n}, {', '.join(map(str, marks.get(f's{n}', (0, 0, 0))))})" for n in range(1, total + 1))
    return f"SELECT site, kept, then_used, else_used FROM (VALUES {rows}) t(site, kept, then_used, else_used)"


@registered("qslice_select_enriched", _marks_sql(SELECTION_SITES, s1=(1, 0, 0), s2=(1, 0, 0), s3=(1, 1, 0), s8=(1, 0, 0), s11=(1, 0, 0)))
def _(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return marks_frame(run, _first(run, ["B"]))


@registered("qslice_select_simple", _marks_sql(SELECTION_SITES, s1=(1, 0, 0), s2=(1, 0, 0), s3=(1, 1, "(SELECT CAST(count(*) > 0 AS INTEGER) FROM lineitem WHERE l_quantity <> 3)"), s8=(1, 0, 0), s11=(1, 0, 0)))
def _(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return marks_frame(run, _first(run, ["B"]).closed())


@registered("qslice_union", _marks_sql(10, s1=(1, 0, 0), s2=(1, 0, 0), s3=(1, 0, 0), s4=(1, 0, 0), s6=(1, 0, 0)))
def _(spark, d):
    run = trace(w.projection_and_constant(), w.catalog(spark, d, "part"))
    return marks_frame(run, Target.where(run, F.col("lbl").startswith("1."), ["B"]))


def _select_diff(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    outer = _first(run, ["B"])
    label = run.value().select("lbl").orderBy("lbl").first()[0]
    return Target.cells(run, {label: []}), outer


@registered("diff_select_inputs", f"SELECT 'lineitem' AS source_table, lbl, unnest(['l_quantity', 'l_extendedprice']) AS \"column\", unnest([2, 1]) AS level FROM ({_FIRST_LINE}) t")
def _(spark, d):
    """The inner pattern knows only that the element is there; the outer one asks its price."""
    inner, outer = _select_diff(spark, d)
    return diff_inputs(inner, outer)["lineitem"].select(F.lit("lineitem").alias("source_table"), "lbl", "column", F.col("level").cast("int").alias("level"))


@registered("diff_select_two_passes", SQL["diff_select_inputs"])
def _(spark, d):
    inner, outer = _select_diff(spark, d)
    return diff_inputs(inner, outer, one_pass=False)["lineitem"].select(F.lit("lineitem").alias("source_table"), "lbl", "column", F.col("level").cast("int").alias("level"))


@registered("diff_select_query", _marks_sql(SELECTION_SITES, s1=(2, 0, 0), s2=(2, 0, 0), s3=(2, 2, 0), s8=(2, 0, 0), s11=(1, 0, 0)))
def _(spark, d):
    return diff_query(*_select_diff(spark, d))


@registered("diff_select_trace", f"SELECT 3 AS site, lbl, true AS branch, 2 AS level FROM ({_FIRST_LINE}) t")
def _(spark, d):
    return diff_trace(*_select_diff(spark, d))


@registered("diff_workflow_inputs", "SELECT t AS source_table, CAST(k AS VARCHAR) AS lbl, 'value' AS \"column\", 2 AS level FROM (VALUES ('T', 3), ('T', 4), ('U', 5)) v(t, k)")
def _(spark, d):
    """All inputs of the result's value are needed for its presence alone: the difference is only the product."""
    run = trace(w.workflow(), w.workflow_catalog(spark, d))
    inner, outer = Target.cells(run, {"3.4.5": []}), Target.cells(run, {"3.4.5": ["value"]})
    parts = diff_inputs(inner, outer)
    return reduce(DataFrame.unionByName, [df.select(F.lit(t).alias("source_table"), "lbl", "column", F.col("level").cast("int").alias("level")) for t, df in parts.items()])


# --- replay ------------------------------------------------------------------------------------------------------------


def _edited(run, fn) -> Catalog:
    return run.cat.replaced("lineitem", fn(run.cat["lineitem"]))


def _replay_query(name: str, fn, sql: str):
    @registered(name, sql)
    def _(spark, d):
        run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
        return replay(run, _edited(run, fn)).failures


_NONE = "SELECT 0 AS site, '' AS lbl, '' AS reason WHERE false"
_replay_query("replay_select_same", lambda df: df, _NONE)
_replay_query("replay_select_price", lambda df: df.withColumn("l_extendedprice", F.col("l_extendedprice") + 1), _NONE)
_replay_query("replay_select_delete", lambda df: df.filter("l_orderkey % 3 <> 0"), _NONE)
_replay_query("replay_select_flip", lambda df: df.withColumn("l_quantity", F.when(F.col("l_orderkey") < 50, F.col("l_quantity") + 1).otherwise(F.col("l_quantity"))), f"SELECT 3 AS site, lbl, 'branch flipped' AS reason FROM ({LINES}) t WHERE l_orderkey < 50 AND l_quantity IN (2, 3)")
_replay_query("replay_select_insert", lambda df: df.unionByName(df.filter("l_orderkey < 5").withColumn("_l0", F.col("_l0") + 100_000_000)), f"SELECT site, lbl, reason FROM (SELECT concat_ws('.', 100000000 + l_orderkey, l_linenumber, split_part(lbl, '.', 3)) AS lbl FROM ({LINES}) t WHERE l_orderkey < 5) n, (SELECT 2 AS site, 'unknown label' AS reason) r")


@registered("replay_select_drop_field", "SELECT reason, CAST(count(*) AS BIGINT) AS elements FROM (SELECT 'missing field' AS reason FROM lineitem) t GROUP BY reason")
def _(spark, d):
    """A lost field fails the replay at every element that has it read."""
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    failures = replay(run, run.cat.apply(Edits("lineitem").drop_field("l_quantity"))).failures
    fields = failures.select(F.split("lbl", r"\.")[0].alias("table"), "reason")
    met = reached(run.blocks[0], run.cat, 1, run.blocks[0].gens[0]).select(F.lit("lineitem").alias("table"))
    return met.join(F.broadcast(fields), "table").groupBy("reason").agg(F.count("*").alias("elements"))


@registered("replay_slice_ignores_rest", _NONE)
def _(spark, d):
    """Within an open slice, new elements, lost columns and flips elsewhere are of no concern."""
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    target = _first(run, ["B"])
    label = tuple(map(int, run.value().select("lbl").orderBy("lbl").first()[0].split(".")))
    keep = (F.col("_l0") == label[0]) & (F.col("_l1") == label[1]) & (F.col("_l2") == label[2])
    changed = _edited(run, lambda df: df.withColumn("l_quantity", F.when(keep, F.col("l_quantity")).otherwise(F.lit(3.0))).unionByName(df.limit(5).withColumn("_l0", F.col("_l0") + 100_000_000)).drop("l_partkey"))
    return replay_slice(slice_trace(run, target), changed).failures


@registered("replay_join_delete", _NONE)
def _(spark, d):
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    return replay(run, run.cat.replaced("customer", run.cat["customer"].filter("c_custkey % 2 = 0"))).failures


@registered("replay_join_flip", "SELECT 5 AS site, concat_ws('.', c_custkey, s_suppkey) AS lbl, 'branch flipped' AS reason FROM customer, (SELECT * FROM supplier WHERE s_suppkey = 9) s WHERE (c_nationkey = s_nationkey) <> (c_nationkey = (s_nationkey + 1) % 25)")
def _(spark, d):
    """One supplier moves to the next nation: pairs that joined no longer do, and others now would."""
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    moved = run.cat["supplier"].withColumn("s_nationkey", F.when(F.col("s_suppkey") == 9, (F.col("s_nationkey") + 1) % 25).otherwise(F.col("s_nationkey")))
    return replay(run, run.cat.replaced("supplier", moved)).failures


@registered("replay_precheck", f"SELECT 3 AS site, lbl, 'branch flipped' AS reason FROM ({_FIRST_LINE}) t")
def _(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    label = tuple(map(int, run.value().select("lbl").orderBy("lbl").first()[0].split(".")))
    return can_replay(run, Edits("lineitem").update(label, "l_quantity", 4.0))


@registered("replay_recompute", f"SELECT lbl, l_extendedprice + 1 AS \"B\" FROM ({LINES}) t WHERE l_quantity = 3 ORDER BY lbl LIMIT 1")
def _(spark, d):
    """The explained part alone, over edited inputs."""
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return recompute(slice_trace(run, _first(run, ["B"])), _edited(run, lambda df: df.withColumn("l_extendedprice", F.col("l_extendedprice") + 1))).select("lbl", "B")


@registered("replay_inside_demand", f"SELECT 'lineitem' AS \"table\", lbl, 'changed' AS reason FROM ({_FIRST_LINE}) t")
def _(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return inside_demand(slice_trace(run, _first(run, ["B"])), _edited(run, lambda df: df.withColumn("l_extendedprice", F.col("l_extendedprice") + 1)))


# --- patterns ----------------------------------------------------------------------------------------------------------


def _demand(spark, d, modulus: int, column: str, rest: str) -> Demand:
    cat = w.catalog(spark, d, "part")
    rows = cat["part"].filter(F.col("p_partkey") % modulus == 0).select("_l0", *[F.lit(int(c == column)).alias(f"m_{c}") for c in ("p_size", "p_retailprice")])
    return Demand("part", rows, rest, ["p_size", "p_retailprice"])


def _pattern_rows(dm: Demand) -> DataFrame:
    return dm.rows.select(F.col("_l0").cast("string").alias("lbl"), F.col("m_p_size").cast("int").alias("m_size"), F.col("m_p_retailprice").cast("int").alias("m_price"), F.lit(dm.rest).alias("rest"))


def _join_pattern(name: str, left: str, right: str, rest: str, default_left: int, default_right: int):
    """Even parts' sizes joined with the prices of parts divisible by six (by three where both sides are open)."""
    other = 6 if CLOSED in (left, right) else 3

    @registered(name, f"SELECT CAST(p_partkey AS VARCHAR) AS lbl, CASE WHEN p_partkey % 2 = 0 THEN greatest(1, CASE WHEN p_partkey % {other} = 0 THEN 0 ELSE {default_right} END) ELSE {default_left} END AS m_size, CASE WHEN p_partkey % {other} = 0 THEN 1 ELSE greatest({default_right}, CASE WHEN p_partkey % 2 = 0 THEN 0 ELSE {default_left} END) END AS m_price, '{rest}' AS rest FROM part WHERE p_partkey % 2 = 0 OR p_partkey % {other} = 0")
    def _(spark, d):
        found, excluded = frames.join(_demand(spark, d, 2, "p_size", left), _demand(spark, d, other, "p_retailprice", right))
        return _pattern_rows(found)


_join_pattern("pat_join_closed_open", CLOSED, SKIP, CLOSED, 0, 0)
_join_pattern("pat_join_skip_skip", SKIP, SKIP, SKIP, 0, 0)
_join_pattern("pat_join_skip_same", SKIP, SAME, SAME, 0, 1)
_join_pattern("pat_join_same_same", SAME, SAME, SAME, 1, 1)


@registered("pat_join_excluded", "SELECT CAST(p_partkey AS VARCHAR) AS lbl FROM part WHERE p_partkey % 3 = 0 AND p_partkey % 2 <> 0")
def _(spark, d):
    """Elements that a closed side excludes: the join does not exist."""
    return frames.join(_demand(spark, d, 2, "p_size", CLOSED), _demand(spark, d, 3, "p_retailprice", SKIP))[1].select(F.col("_l0").cast("string").alias("lbl"))


@registered("pat_plus", "SELECT CAST(p_partkey AS VARCHAR) AS lbl, CAST(p_partkey % 2 = 0 AS INTEGER) AS m_size, CAST(p_partkey % 2 <> 0 AS INTEGER) AS m_price, 'skip' AS rest FROM part WHERE p_partkey % 2 = 0 OR p_partkey % 3 = 0")
def _(spark, d):
    odd = _demand(spark, d, 3, "p_retailprice", SKIP)
    odd.rows = odd.rows.filter("_l0 % 2 <> 0")
    return _pattern_rows(frames.plus(_demand(spark, d, 2, "p_size", SAME), odd))


@registered("pat_harden", "SELECT CAST(p_partkey AS VARCHAR) AS lbl, 1 AS m_size, 1 AS m_price, 'same' AS rest FROM part WHERE p_partkey % 2 = 0")
def _(spark, d):
    return _pattern_rows(frames.harden(_demand(spark, d, 2, "p_size", SKIP)))


@registered("pat_under_prepend", "SELECT CAST(p_partkey AS VARCHAR) AS lbl, 1 AS m_size, 0 AS m_price, 'skip' AS rest FROM part WHERE p_partkey % 2 = 0")
def _(spark, d):
    """A label put in front and taken off again."""
    return _pattern_rows(frames.under(frames.prepend(_demand(spark, d, 2, "p_size", SKIP), (1, 7)), (1, 7)))


@registered("pat_restrict", "SELECT CAST(p_partkey AS VARCHAR) AS lbl, 1 AS m_size, 0 AS m_price, 'closed' AS rest FROM part WHERE p_partkey % 2 = 0 AND p_size = 3")
def _(spark, d):
    code = w.catalog(spark, d, "part")["part"].filter("p_size = 3").select("_l0")
    return _pattern_rows(frames.restrict(_demand(spark, d, 2, "p_size", CLOSED), code))


def _equiv(name: str, rest: str, sql: str):
    @registered(name, sql)
    def _(spark, d):
        """Sizes of parts divisible by four grow; parts divisible by ten go."""
        cat = w.catalog(spark, d, "part")
        other = cat.replaced("part", cat["part"].filter("p_partkey % 10 <> 0").withColumn("p_size", F.when(F.col("p_partkey") % 4 == 0, F.col("p_size") + 1).otherwise(F.col("p_size"))))
        return frames.equiv_violations(_demand(spark, d, 2, "p_size", rest), cat, other)


_LISTED = "SELECT CAST(p_partkey AS VARCHAR) AS lbl, CASE WHEN p_partkey % 10 = 0 THEN 'missing' ELSE 'changed' END AS reason FROM part WHERE p_partkey % 2 = 0 AND (p_partkey % 10 = 0 OR p_partkey % 4 = 0)"
_equiv("pat_equiv_skip", SKIP, _LISTED)
_equiv("pat_equiv_same", SAME, _LISTED)
_equiv("pat_equiv_closed", CLOSED, f"{_LISTED} UNION ALL SELECT CAST(p_partkey AS VARCHAR), 'unlisted' FROM part WHERE p_partkey % 2 <> 0")


# --- provenance --------------------------------------------------------------------------------------------------------


@registered("lineage_join", "SELECT DISTINCT concat_ws('.', c_custkey, s_suppkey) AS lbl, unnest(['customer', 'supplier']) AS source_table, unnest([CAST(c_custkey AS VARCHAR), CAST(s_suppkey AS VARCHAR)]) AS source FROM customer JOIN supplier ON c_nationkey = s_nationkey")
def _(spark, d):
    return provenance.lineage(trace(w.join(), w.catalog(spark, d, "customer", "supplier")))


_REGION = "FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey"
_WITNESS = "CASE WHEN a.n_nationkey = b.n_nationkey THEN concat('nation:', a.n_nationkey) ELSE array_to_string(list_sort([concat('nation:', a.n_nationkey), concat('nation:', b.n_nationkey)]), ' ') END"


@registered("why_regions", f"SELECT DISTINCT a.n_regionkey AS region, {_WITNESS} AS witness {_REGION}")
def _(spark, d):
    return provenance.why(trace(w.region_pairs(), w.catalog(spark, d, "nation")))


@registered("why_minimal_regions", "SELECT n_regionkey AS region, concat('nation:', n_nationkey) AS witness FROM nation")
def _(spark, d):
    return provenance.why(trace(w.region_pairs(), w.catalog(spark, d, "nation")), minimal=True)


@registered("how_regions", f"SELECT a.n_regionkey AS region, array_to_string(list_sort([concat('nation:', a.n_nationkey), concat('nation:', b.n_nationkey)]), '*') AS monomial, count(*) AS coefficient {_REGION} GROUP BY 1, 2")
def _(spark, d):
    return provenance.how(trace(w.region_pairs(), w.catalog(spark, d, "nation")))


def _ring(name: str, ring: str, sql: str):
    @registered(name, sql)
    def _(spark, d):
        return provenance.eval_semiring(provenance.how(trace(w.region_pairs(), w.catalog(spark, d, "nation"))), ring)


_ring("how_counting", "counting", f"SELECT a.n_regionkey AS region, count(*) AS value {_REGION} GROUP BY 1")
_ring("how_boolean", "boolean", f"SELECT a.n_regionkey AS region, true AS value {_REGION} GROUP BY 1")
_ring("how_min_cost", "min_cost", f"SELECT a.n_regionkey AS region, CAST(2 AS BIGINT) AS value {_REGION} GROUP BY 1")


@registered("how_delete_join", "SELECT concat_ws('.', c_custkey, s_suppkey) AS lbl FROM customer JOIN supplier ON c_nationkey = s_nationkey WHERE s_suppkey % 2 <> 0")
def _(spark, d):
    """Even suppliers go; what survives is told from lineage alone."""
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    gone = run.cat["supplier"].filter("s_suppkey % 2 = 0").select(F.col("_l0").cast("string").alias("source"))
    return provenance.how_delete(run, "supplier", gone)


@registered("where_join", "SELECT concat_ws('.', c_custkey, s_suppkey) AS lbl, unnest(['A', 'B']) AS field, unnest(['customer', 'supplier']) AS source_table, unnest([CAST(c_custkey AS VARCHAR), CAST(s_suppkey AS VARCHAR)]) AS source, unnest(['c_acctbal', 's_name']) AS source_column FROM customer JOIN supplier ON c_nationkey = s_nationkey")
def _(spark, d):
    return provenance.where(trace(w.join(), w.catalog(spark, d, "customer", "supplier")))


@registered("impact_nation", "SELECT concat_ws('.', c_custkey, s_suppkey) AS lbl, '*' AS field FROM customer JOIN supplier ON c_nationkey = s_nationkey WHERE s_suppkey = 9")
def _(spark, d):
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    return provenance.impact(run, "supplier", run.cat["supplier"].filter("s_suppkey = 9").select("_l0"), "s_nationkey")


@registered("impact_name", "SELECT concat_ws('.', c_custkey, s_suppkey) AS lbl, 'B' AS field FROM customer JOIN supplier ON c_nationkey = s_nationkey WHERE s_suppkey = 9")
def _(spark, d):
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    return provenance.impact(run, "supplier", run.cat["supplier"].filter("s_suppkey = 9").select("_l0"), "s_name")


@registered("equal_except", f"SELECT lbl FROM ({LINES}) t WHERE l_quantity = 3 AND l_orderkey % 2 = 0 AND l_orderkey > 100")
def _(spark, d):
    """Prices of even orders change; orders up to 100 are excepted."""
    cat = w.catalog(spark, d, "lineitem")
    run = trace(w.selection(), cat)
    changed = _edited(run, lambda df: df.withColumn("l_extendedprice", F.col("l_extendedprice") + F.when(F.col("l_orderkey") % 2 == 0, 1).otherwise(0)))
    few = run.value().filter(F.split("lbl", r"\.")[0].cast("long") <= 100).select("lbl")
    return provenance.equal_except_at(run.value(), evaluate(w.selection(), changed), few)


@registered("graph_join", "SELECT concat('result:', l) AS node, 'generated_by' AS relation, concat('step0:', l) AS \"to\" FROM (SELECT concat_ws('.', c_custkey, s_suppkey) AS l FROM customer JOIN supplier ON c_nationkey = s_nationkey) t UNION SELECT concat('step0:', concat_ws('.', c_custkey, s_suppkey)), 'used', unnest([concat('customer:', c_custkey), concat('supplier:', s_suppkey)]) FROM customer JOIN supplier ON c_nationkey = s_nationkey")
def _(spark, d):
    return provenance.export_graph(trace(w.join(), w.catalog(spark, d, "customer", "supplier")))


@registered("triples_join", f"SELECT concat('result:', l) AS subject, unnest(['field A', 'field B', 'generated_by']) AS predicate, unnest([a, b, concat('step0:', l)]) AS object FROM (SELECT concat_ws('.', c_custkey, s_suppkey) AS l, CAST(c_nationkey AS VARCHAR) AS a, s_name AS b FROM customer JOIN supplier ON c_nationkey = s_nationkey WHERE (c_custkey, s_suppkey) IN (SELECT c_custkey, s_suppkey FROM ({_PAIRS}) p WHERE r = 1)) t UNION ALL SELECT concat('step0:', concat_ws('.', c_custkey, s_suppkey)), 'used', unnest([concat('customer:', c_custkey), concat('supplier:', s_suppkey)]) FROM ({_PAIRS}) p WHERE r = 1")
def _(spark, d):
    """The triples of one result element's part of the run."""
    from backtrail.plans.expr import query, rec, table

    q = query({"x": table("customer"), "y": table("supplier")}, rec(A=w.f(w.x, "c_nationkey"), B=w.f(w.y, "s_name")), w.f(w.x, "c_nationkey").eq(w.f(w.y, "s_nationkey")))
    run = trace(q, w.catalog(spark, d, "customer", "supplier"))
    first = first_labels(run, by_number=True)[0]
    return provenance.sub_run(provenance.export_triples(run), [first])


@registered("trail_join", f"WITH RECURSIVE edges AS ({SQL['graph_join']}), reach(node) AS (SELECT concat('result:', c_custkey, '.', s_suppkey) FROM ({_PAIRS}) p WHERE r <= 3 UNION SELECT e.\"to\" FROM edges e JOIN reach r ON e.node = r.node) SELECT node FROM reach")
def _(spark, d):
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    first = run.value().orderBy(F.split("lbl", r"\.").cast("array<int>")).limit(3)
    return provenance.trail(provenance.export_graph(run), first.select(F.concat(F.lit("result:"), F.col("lbl")).alias("node")), 2)


@registered("redact_select", f"SELECT 'lineitem' AS source_table, lbl, 'l_extendedprice' AS \"column\" FROM ({_FIRST_LINE}) t")
def _(spark, d):
    """Hiding prices hides a demanded cell: the result can't be recomputed from what is left."""
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return provenance.redact(slice_trace(run, _first(run, ["B"])), {"lineitem": ["l_extendedprice", "l_tax"]})[1]


# --- measures and guarantees -------------------------------------------------------------------------------------------


@registered("measure_nodes", f"SELECT 'select' AS name, 2 + 6 * count(*) + 5 * count(*) FILTER (l_quantity = 3) AS full_nodes, CAST(11 AS BIGINT) AS open_nodes, 2 + 6 * count(*) + 3 AS closed_nodes FROM lineitem UNION ALL SELECT 'workflow', 2 + 2 * n + 2 * n * n + 17 * n * n * n + 3 * k, CAST(26 AS BIGINT), 2 + 2 * n + 2 * n * n + 17 * n * n * n + 3 FROM (SELECT count(*) AS n FROM {_TRIPLES} t) s, (SELECT count(*) AS k {_WORKFLOW}) r")
def _(spark, d):
    """Nodes of the full trace, of the open slice of one cell, of the closed one."""
    out = []
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    out.append(("select", measure.nodes(run, _first(run, ["B"]))))
    run = trace(w.workflow(), w.workflow_catalog(spark, d))
    out.append(("workflow", measure.nodes(run, Target.cells(run, {"3.4.5": ["value"]}))))
    return spark.createDataFrame([(k, n["full"], n["open"], n["closed"]) for k, n in out], "name string, full_nodes long, open_nodes long, closed_nodes long")


@registered("measure_kept_fraction", f"SELECT 'customer' AS source_table, CAST(2 AS BIGINT) AS kept_cells, 5 * (SELECT count(*) FROM customer) AS cells UNION ALL SELECT 'supplier', 2 * count(*), 4 * (SELECT count(*) FROM supplier) FROM ({_PAIRS}) p WHERE c_custkey = (SELECT min(c_custkey) FROM ({_PAIRS}) q)")
def _(spark, d):
    """Cells that the pairs of one customer rest on, of all cells."""
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    own = plan.gen_labels(run.cat, run.blocks[0].gens[0])[0]
    first = int(first_labels(run, by_number=True)[0].split(".")[0])
    return measure.kept_fraction(run, Target.where(run, F.col(own) == first, ["A", "B"]))


@registered("measure_growth", "SELECT n, 2 + 2 * n + 2 * n * n + 17 * n * n * n + 3 * (SELECT count(*) FROM range(1, n + 1) a(v), range(1, n + 1) b(v), range(1, n + 1) c(v) WHERE a.v < b.v AND a.v * a.v + b.v * b.v = c.v * c.v) AS tree, CAST(27 AS BIGINT) AS shared FROM (VALUES (CAST(10 AS BIGINT)), (20), (40)) t(n)")
def _(spark, d):
    """Trace size as a tree grows as the number of generators says; shared, it is the query's own size."""
    rows = measure.growth(lambda _: w.workflow(), [(n, w.workflow_catalog(spark, d, n)) for n in (10, 20, 40)])
    return spark.createDataFrame([(r["n"], r["tree"], r["shared"]) for r in rows], "n long, tree long, shared long")


@registered("measure_label_depth", "SELECT name, CAST(depth AS BIGINT) AS depth FROM (VALUES ('select', 3), ('swap', 4), ('join', 2), ('workflow', 3)) t(name, depth)")
def _(spark, d):
    """Parts in the labels of the results' own elements."""
    cat = w.catalog(spark, d, "lineitem", "customer", "supplier")
    runs = {"select": trace(w.selection(), cat), "swap": trace(w.swap(), cat), "join": trace(w.join(), cat), "workflow": trace(w.workflow(), w.workflow_catalog(spark, d))}
    return reduce(DataFrame.unionByName, [measured_depth(r).select(F.lit(k).alias("name"), "depth") for k, r in runs.items()])


def _selected(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    return run, _first(run, ["B"])


def _joined(spark, d):
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    return run, _join_target(run)


def _guaranteed(spark, d):
    return {"select": _selected(spark, d), "join": _joined(spark, d)}


def _traced(spark, d):
    return {"select": trace(w.selection(), w.catalog(spark, d, "lineitem")), "join": trace(w.join(), w.catalog(spark, d, "customer", "supplier"))}


@registered("check_slices", zero_sql("join", "join closed", "select", "select closed"))
def _(spark, d):
    """Whatever changes outside a slice, its target stays."""
    runs = _guaranteed(spark, d)
    return counted(spark, {k: checks.slice_violations(r, t) for k, (r, t) in runs.items()} | {f"{k} closed": checks.slice_violations(r, t.closed()) for k, (r, t) in runs.items()})


@registered("check_query_slices", zero_sql("join", "select"))
def _(spark, d):
    return counted(spark, {k: checks.query_slice_violations(r, t) for k, (r, t) in _guaranteed(spark, d).items()})


@registered("check_control", "SELECT 'select' AS name, true AS damaged")
def _(spark, d):
    """The check can fail: altering a kept condition cell does damage."""
    run, target = _selected(spark, d)
    return checks.slice_violations(run, target, strike=("lineitem", "l_quantity")).agg((F.count("*") > 0).alias("damaged")).select(F.lit("select").alias("name"), "damaged")


@registered("check_consistency", zero_sql("join", "select"))
def _(spark, d):
    return counted(spark, {k: checks.consistency_violations(r) for k, r in _traced(spark, d).items()})


@registered("check_determinacy", zero_sql("join", "select"))
def _(spark, d):
    return counted(spark, {k: checks.determinacy_violations(r) for k, r in _traced(spark, d).items()})


@registered("check_monotone", zero_sql("cells", "elements"))
def _(spark, d):
    inner, outer = _select_diff(spark, d)
    return counted(spark, {"cells": checks.monotone_violations(inner, outer), "elements": leq(inner, outer)})


@registered("check_fidelity", "SELECT name, ok, fresh FROM (VALUES ('delete', true, true), ('flip', false, false), ('insert', false, false), ('price', true, true)) t(name, ok, fresh)")
def _(spark, d):
    run = trace(w.selection(), w.catalog(spark, d, "lineitem"))
    label = tuple(map(int, run.value().select("lbl").orderBy("lbl").first()[0].split(".")))
    edits = {"price": Edits("lineitem").update(label, "l_extendedprice", 1.0), "flip": Edits("lineitem").update(label, "l_quantity", 9.0), "delete": Edits("lineitem").delete(label), "insert": Edits("lineitem").insert((10**9, 1, 1), l_orderkey=10**9, l_linenumber=1, l_quantity=3.0)}
    return spark.createDataFrame([(k, *checks.fidelity(run, e)) for k, e in edits.items()], "name string, ok boolean, fresh boolean")
