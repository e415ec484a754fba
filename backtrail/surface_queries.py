"""Registered queries of the operators around the methods: joins, groupings, windows, functions, sources and sinks, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from backtrail import workloads as w
from backtrail.functions import udfs
from backtrail.operators import joins
from backtrail.operators.runs import evaluate, trace
from backtrail.operators.slicing import Target, first_labels, slice_trace
from backtrail.plans import compile as plan
from backtrail.sources import io
from backtrail.streaming import streams

QUERIES: dict = {}
SQL: dict[str, str] = {}


def registered(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return add


def table(spark, d, name):
    return spark.read.parquet(f"{d}/{name}.parquet")


def scratch(spark) -> str:
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if base is None:
        import tempfile

        base = tempfile.mkdtemp(prefix="scratch-")
    return f"{base}/scratch-{uuid.uuid4().hex}"


CENTS = "CAST(round({} * 100) AS BIGINT)"


def cents(c: str):
    return F.round(F.col(c) * 100).cast("long")


# --- joins -------------------------------------------------------------------------------------------------------------


@registered("surface_range_join", "SELECT p_partkey, lo FROM part JOIN (SELECT i * 10 AS lo, i * 10 + 15 AS hi FROM range(5) t(i)) b ON p_size >= lo AND p_size < hi")
def _(spark, d):
    bands = spark.range(5).select((F.col("id") * 10).alias("lo"), (F.col("id") * 10 + 15).alias("hi"))
    return joins.range_join(table(spark, d, "part").select("p_partkey", "p_size"), bands, "p_size", "lo", "hi", 10).select("p_partkey", "lo")


@registered("surface_interval_join", "SELECT a.p_partkey AS a, count(*) AS n, CAST(sum(b.p_partkey) AS BIGINT) AS keys FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_size < b.p_size + 3 AND b.p_size < a.p_size + 3 GROUP BY 1")
def _(spark, d):
    """The interval join over all parts; of each part the number of its partners and the sum of their keys."""
    part = table(spark, d, "part")
    left = part.select(F.col("p_partkey").alias("a"), "p_brand", F.col("p_size").alias("s"), (F.col("p_size") + 3).alias("e"))
    right = part.select(F.col("p_partkey").alias("b"), "p_brand", F.col("p_size").alias("s2"), (F.col("p_size") + 3).alias("e2"))
    pairs = joins.interval_join(left, right, ["p_brand"], "s", "e", "s2", "e2", 3)
    return pairs.groupBy("a").agg(F.count("*").alias("n"), F.sum("b").alias("keys"))


@registered("surface_asof_join", "SELECT a.event_id, b.cents FROM (SELECT * FROM events WHERE event_type = 'view') a ASOF LEFT JOIN (SELECT user_id, ts, max(CAST(round(value * 100) AS BIGINT)) AS cents FROM events WHERE event_type = 'purchase' GROUP BY user_id, ts) b ON a.user_id = b.user_id AND a.ts >= b.ts")
def _(spark, d):
    """Each view with the user's last purchase before it."""
    events = table(spark, d, "events")
    views = events.filter("event_type = 'view'").select("event_id", "user_id", "ts")
    bought = events.filter("event_type = 'purchase'").select("user_id", "ts", cents("value").alias("cents"))
    return joins.asof_join(views, bought, ["user_id"], "ts", ["cents"]).select("event_id", "cents")


@registered("surface_salted_join", "SELECT c_custkey, s_suppkey FROM customer JOIN supplier ON c_nationkey = s_nationkey")
def _(spark, d):
    left = table(spark, d, "customer").select("c_custkey", F.col("c_nationkey").alias("k"))
    right = table(spark, d, "supplier").select("s_suppkey", F.col("s_nationkey").alias("k"))
    return joins.salted_join(left, right, ["k"]).select("c_custkey", "s_suppkey")


@registered("surface_salted_sum", f"SELECT l_returnflag, CAST(sum({CENTS.format('l_extendedprice')}) AS BIGINT) AS total FROM lineitem GROUP BY 1")
def _(spark, d):
    rows = table(spark, d, "lineitem").select("l_orderkey", "l_returnflag", cents("l_extendedprice").alias("total"))
    return joins.salted_sum(rows, ["l_returnflag"], ["total"])


@registered("surface_semi_join", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority LIKE '1%')")
def _(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders").filter("o_orderpriority like '1%'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@registered("surface_anti_join", "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 45)")
def _(spark, d):
    return table(spark, d, "part").join(table(spark, d, "lineitem").filter("l_quantity > 45"), F.col("p_partkey") == F.col("l_partkey"), "left_anti").select("p_partkey")


@registered("surface_outer_join", "SELECT c_custkey AS k, o_orderkey, CASE WHEN o_orderkey IS NULL THEN 2 ELSE 1 END AS branch FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_orderstatus = 'P') o ON c_custkey = o_custkey")
def _(spark, d):
    left = table(spark, d, "customer").select(F.col("c_custkey").alias("k"))
    right = table(spark, d, "orders").filter("o_orderstatus = 'P'").select(F.col("o_custkey").alias("k"), "o_orderkey")
    return joins.outer_join(left, right, ["k"], ["o_orderkey"])


@registered("surface_full_join", "SELECT c_custkey, s_suppkey FROM customer FULL JOIN supplier ON floor(c_acctbal) = floor(s_acctbal)")
def _(spark, d):
    """Whole tables, matched by balance in whole units; both sides have rows without a match."""
    a, b = table(spark, d, "customer").select("c_custkey", "c_acctbal"), table(spark, d, "supplier").select("s_suppkey", "s_acctbal")
    return a.join(b, F.floor("c_acctbal") == F.floor("s_acctbal"), "full").select("c_custkey", "s_suppkey")


@registered("surface_join_strategies", "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark, d):
    """A merge join asked for by a hint; broadcast only behind a count."""
    lines, orders = table(spark, d, "lineitem").select("l_orderkey"), table(spark, d, "orders").select("o_orderkey", "o_orderstatus")
    return lines.join(orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


# --- aggregates, groupings, windows, sets ------------------------------------------------------------------------------


@registered("surface_aggregates", f"SELECT l_returnflag, l_linestatus, count(*) AS n, count(DISTINCT l_partkey) AS parts, CAST(sum({CENTS.format('l_extendedprice')}) AS BIGINT) AS total, min(l_shipdate) AS first, max(l_shipdate) AS last, round(avg(l_quantity), 4) AS mean, round(stddev_samp(l_quantity), 4) AS spread FROM lineitem GROUP BY 1, 2")
def _(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.countDistinct("l_partkey").alias("parts"), F.sum(cents("l_extendedprice")).alias("total"), F.min("l_shipdate").alias("first"), F.max("l_shipdate").alias("last"), F.round(F.avg("l_quantity"), 4).alias("mean"), F.round(F.stddev_samp("l_quantity"), 4).alias("spread")
    )


@registered("surface_approx_distinct", "SELECT true AS close")
def _(spark, d):
    got = table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("a"), F.countDistinct("l_partkey").alias("b"))
    return got.select((F.abs(F.col("a") - F.col("b")) < 0.15 * F.col("b")).alias("close"))


_SETS = "SELECT {a} AS l_returnflag, {b} AS l_linestatus, count(*) AS n, {k} AS branch FROM lineitem GROUP BY {g}"


@registered("surface_grouping_sets", " UNION ALL ".join((_SETS.format(a="l_returnflag", b="l_linestatus", k=1, g="1, 2"), _SETS.format(a="l_returnflag", b="NULL", k=2, g="1"), "SELECT NULL, NULL, count(*), 3 FROM lineitem")))
def _(spark, d):
    """Groupings with a branch each, as slices see them."""
    return joins.grouped_sets(table(spark, d, "lineitem"), [["l_returnflag", "l_linestatus"], ["l_returnflag"], []], [F.count("*").alias("n")])


@registered("surface_cube", "SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY CUBE (p_brand, p_type)")
def _(spark, d):
    return table(spark, d, "part").cube("p_brand", "p_type").agg(F.count("*").alias("n"))


@registered("surface_rollup", "SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY ROLLUP (p_brand, p_type)")
def _(spark, d):
    return table(spark, d, "part").rollup("p_brand", "p_type").agg(F.count("*").alias("n"))


@registered("surface_windows", f"SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, CAST(sum({CENTS.format('o_totalprice')}) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS running FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def _(spark, d):
    by = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, d, "orders").select(
        "o_orderkey", F.row_number().over(by).cast("long").alias("rn"), F.rank().over(by).cast("long").alias("rk"), F.dense_rank().over(by).cast("long").alias("dr"), F.ntile(4).over(by).cast("long").alias("nt"),
        F.lag("o_orderkey").over(by).alias("before"), F.lead("o_orderkey").over(by).alias("after"), F.sum(cents("o_totalprice")).over(by.rowsBetween(-2, 0)).alias("running"),
    )


@registered("surface_top_k", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) t WHERE r <= 2")
def _(spark, d):
    return joins.top_k(table(spark, d, "orders"), ["o_custkey"], [F.desc("o_totalprice"), F.asc("o_orderkey")], 2).select("o_custkey", "o_orderkey")


@registered("surface_sort_limit", "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10")
def _(spark, d):
    return table(spark, d, "part").orderBy(F.desc("p_retailprice"), "p_partkey").limit(10).select("p_partkey", "p_retailprice")


@registered("surface_sets", "(SELECT 'union' AS kind, c_nationkey AS k FROM customer UNION SELECT 'union', s_nationkey FROM supplier) UNION ALL (SELECT 'intersect', k FROM (SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier) a) UNION ALL (SELECT 'except all', k FROM (SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier) b)")
def _(spark, d):
    a, b = table(spark, d, "customer").select(F.col("c_nationkey").alias("k")), table(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))
    named = lambda n, df: df.select(F.lit(n).alias("kind"), "k")
    return named("union", a.union(b).distinct()).unionByName(named("intersect", a.intersect(b))).unionByName(named("except all", a.exceptAll(b)))


@registered("surface_predicates", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderstatus IN ('F', 'O') AND o_orderpriority LIKE '%-%' AND NOT (o_custkey % 7 = 0 OR o_orderdate IS NULL)")
def _(spark, d):
    c = F.col
    return table(spark, d, "orders").filter(c("o_totalprice").between(1000, 200000) & c("o_orderstatus").isin("F", "O") & c("o_orderpriority").like("%-%") & ~((c("o_custkey") % 7 == 0) | c("o_orderdate").isNull())).select("o_orderkey")


# --- functions ---------------------------------------------------------------------------------------------------------


@registered("surface_strings", "SELECT p_partkey, upper(substring(p_name, 1, 5)) AS head, length(p_name) AS n, concat(p_brand, '/', lower(p_type)) AS joined, replace(p_name, ' ', '_') AS flat FROM part")
def _(spark, d):
    return table(spark, d, "part").select("p_partkey", F.upper(F.substring("p_name", 1, 5)).alias("head"), F.length("p_name").cast("long").alias("n"), F.concat("p_brand", F.lit("/"), F.lower("p_type")).alias("joined"), F.regexp_replace("p_name", " ", "_").alias("flat"))


@registered("surface_dates", "SELECT o_orderkey, date_trunc('month', o_orderdate) AS m, extract(year FROM o_orderdate) AS y, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS days, CAST(o_orderdate AS DATE) + INTERVAL 1 MONTH AS next FROM orders")
def _(spark, d):
    day = F.to_date("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m"), F.year("o_orderdate").cast("long").alias("y"), F.datediff(day, F.lit("1992-01-01").cast("date")).cast("long").alias("days"), F.add_months(day, 1).cast("timestamp_ntz").alias("next"))


@registered("surface_math", "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS root, power(p_size, 2) AS squared, greatest(p_size, 25) AS big, abs(p_size - 25) AS away, p_partkey % 7 AS r FROM part")
def _(spark, d):
    return table(spark, d, "part").select("p_partkey", F.round(F.sqrt("p_retailprice"), 6).alias("root"), F.pow("p_size", F.lit(2)).alias("squared"), F.greatest("p_size", F.lit(25)).alias("big"), F.abs(F.col("p_size") - 25).alias("away"), (F.col("p_partkey") % 7).alias("r"))


@registered("surface_arrays", "SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding[1:8], lambda v: CAST(v AS DOUBLE))), 4) AS head, len(list_filter(embedding, lambda v: v > 0)) AS positive FROM embeddings")
def _(spark, d):
    first = F.transform(F.slice("embedding", 1, 8), lambda v: v.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), F.round(F.aggregate(first, F.lit(0.0), lambda s, v: s + v), 4).alias("head"), F.size(F.filter("embedding", lambda v: v > 0)).cast("long").alias("positive"))


@registered("surface_maps", "SELECT p_partkey, k, v FROM (SELECT p_partkey, unnest(['brand', 'type']) AS k, unnest([p_brand, p_type]) AS v FROM part) t")
def _(spark, d):
    pairs = F.create_map(F.lit("brand"), "p_brand", F.lit("type"), "p_type")
    return table(spark, d, "part").select("p_partkey", F.explode(F.map_entries(pairs)).alias("e")).select("p_partkey", F.col("e.key").alias("k"), F.col("e.value").alias("v"))


@registered("surface_json", "SELECT event_id, json_keys(props) AS keys FROM events")
def _(spark, d):
    return table(spark, d, "events").select("event_id", F.json_object_keys("props").alias("keys"))


@registered("surface_explode", "SELECT doc_id, i - 1 AS position, lines[i] AS line FROM (SELECT doc_id, string_split(text, chr(10)) AS lines, unnest(generate_series(1, len(string_split(text, chr(10))))) AS i FROM documents) t")
def _(spark, d):
    """A text's lines as a nested bag; the position is the label part."""
    return table(spark, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("position", "line")).withColumn("position", F.col("position").cast("long"))


@registered("surface_udtf", SQL["surface_explode"])
def _(spark, d):
    lines = udfs.numbered_lines()
    spark.udtf.register("numbered_lines", lines)
    name = f"documents_{uuid.uuid4().hex}"
    table(spark, d, "documents").createOrReplaceTempView(name)
    return spark.sql(f"SELECT doc_id, CAST(position AS BIGINT) AS position, line FROM {name}, LATERAL numbered_lines(text)")


@registered("surface_udf", "SELECT doc_id, round(len(regexp_extract_all(text, '[aeiou]')) / greatest(length(text), 1), 6) AS share FROM documents")
def _(spark, d):
    share = udfs.vowel_share()
    return table(spark, d, "documents").select("doc_id", F.round(share("text"), 6).alias("share"))


@registered("surface_udaf", "SELECT p_brand, median(p_retailprice) AS mid FROM part GROUP BY p_brand")
def _(spark, d):
    mid = udfs.median_of()
    return table(spark, d, "part").groupBy("p_brand").agg(mid("p_retailprice").alias("mid"))


# --- sources and sinks -------------------------------------------------------------------------------------------------


def _round(kind: str):
    @registered(f"io_{kind}", "SELECT CAST(n_nationkey AS INTEGER) AS n_nationkey, n_name FROM nation")
    def _(spark, d):
        """Written and read again in a format."""
        folder = scratch(spark)
        io.write(table(spark, d, "nation").select("n_nationkey", "n_name"), folder, kind)
        return io.read(spark, folder, kind, "n_nationkey int, n_name string")


for _kind in ("parquet", "csv", "json", "orc"):
    _round(_kind)


@registered("io_partitioned", "SELECT p_partkey, p_brand FROM part")
def _(spark, d):
    folder = scratch(spark)
    io.write(table(spark, d, "part").select("p_partkey", "p_brand"), folder, by=["p_brand"])
    return io.read(spark, folder).select("p_partkey", "p_brand")


@registered("io_slice", "SELECT 'customer' AS name, CAST(1 AS BIGINT) AS n UNION ALL SELECT 'supplier', CAST(1 AS BIGINT)")
def _(spark, d):
    """A slice's demanded cells, written table by table."""
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    first = first_labels(run, by_number=True)[0]
    folder = scratch(spark)
    io.write_slice(slice_trace(run, Target.cells(run, {first: ["A", "B"]})), folder)
    return spark.createDataFrame([(t, spark.read.parquet(f"{folder}/{t}").count()) for t in ("customer", "supplier")], "name string, n long")


@registered("io_trace", "SELECT 5 AS site, count(*) AS n FROM customer JOIN supplier ON c_nationkey = s_nationkey")
def _(spark, d):
    """A trace stored by run and site, and read by site."""
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier").spread("customer"), "lazy")
    folder = scratch(spark)
    io.write_trace(run, "first", folder)
    return spark.read.parquet(folder).filter("run = 'first' AND site = 5").groupBy("site").agg(F.count("*").alias("n"))


@registered("io_sql_views", "SELECT c_custkey, count(*) AS n FROM customer JOIN supplier ON c_nationkey = s_nationkey GROUP BY 1")
def _(spark, d):
    run = trace(w.join(), w.catalog(spark, d, "customer", "supplier"))
    prefix = f"run_{uuid.uuid4().hex}"
    io.as_views(run, prefix)
    customer = plan.gen_labels(run.cat, run.blocks[0].gens[0])[0]
    return spark.sql(f"SELECT {customer} AS c_custkey, count(*) AS n FROM {prefix}_value GROUP BY 1")


@registered("io_snapshot", "SELECT CAST(p_partkey AS VARCHAR) AS lbl, p_size AS size FROM part")
def _(spark, d):
    """Labels frozen in a snapshot, clustered by label, give the same result."""
    return evaluate(w.part_sizes(), w.catalog(spark, d, "part").snapshot(scratch(spark), "part", 4))


# --- streams -----------------------------------------------------------------------------------------------------------

_HOUR = "epoch_us(time_bucket(INTERVAL 1 HOUR, ts))"


@registered("stream_tumbling", f"SELECT concat({_HOUR}, '.', event_type) AS lbl, event_type, count(*) AS n, CAST(sum({CENTS.format('value')}) AS BIGINT) AS cents FROM events GROUP BY {_HOUR}, event_type")
def _(spark, d):
    return streams.drained(streams.tumbling(streams.events(spark, d)), "complete")


@registered("stream_sliding", "SELECT CAST(s AS BIGINT) AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([epoch_us(time_bucket(INTERVAL 1 HOUR, ts)), epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) - 3600000000]) AS s FROM events) t GROUP BY 1, 2")
def _(spark, d):
    return streams.drained(streams.sliding(streams.events(spark, d)), "complete")


_SESSIONS = "SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events) a"


@registered("stream_sessions", f"SELECT epoch_us(min(ts)) AS start, user_id, count(*) AS n FROM ({_SESSIONS}) b GROUP BY user_id, s")
def _(spark, d):
    return streams.drained(streams.sessions(streams.events(spark, d)), "complete")


@registered("stream_without_repeats", "SELECT DISTINCT event_id FROM events")
def _(spark, d):
    df = streams.events(spark, d)
    return streams.drained(streams.without_repeats(df.unionByName(df), ["event_id"]).select("event_id"))


@registered("stream_with_static", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def _(spark, d):
    static = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return streams.drained(streams.with_static(streams.events(spark, d), static, "user_id").select("event_id", "c_mktsegment"))


@registered("stream_running_totals", f"SELECT user_id, count(*) AS n, CAST(sum({CENTS.format('value')}) AS BIGINT) AS cents FROM events GROUP BY 1")
def _(spark, d):
    return streams.drained(streams.running_totals(streams.events(spark, d)), "update")


@registered("stream_unknown_labels", "SELECT event_id FROM events WHERE event_id % 5 = 0")
def _(spark, d):
    """Events that a trace of four fifths of the table does not know."""
    known = table(spark, d, "events").filter("event_id % 5 <> 0")
    return streams.drained(streams.unknown_labels(streams.events(spark, d), known, "event_id").select("event_id"))


@registered("stream_traced", "SELECT CAST(event_id AS VARCHAR) AS lbl, event_type AS kind FROM events WHERE value > 100")
def _(spark, d):
    """A query evaluated and traced batch by batch; the stored trace has the iterations that passed."""
    from backtrail.plans.expr import rec, select
    from backtrail.plans.expr import table as bag_table

    query = select(bag_table("events"), lambda e: w.f(e, "value") > 100, lambda e: rec(kind=w.f(e, "event_type")))
    step = streams.traced(lambda _: query, "events", "event_id", scratch(spark), ["event_id", "event_type", "value"])
    return streams.drained(streams.events(spark, d), each=step)
