"""Example queries over the given tables, each with the catalog it needs and a target."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from backtrail.plans.expr import Agg, Expr, Field, IsEmpty, Var, bag, each, group_agg, grouping_sets, let, lit, minus, op, outer, primitive, query, rec, rename, select, table, union, when
from backtrail.sources.catalog import KEYS, TIES, Catalog

x, y, z = Var("x"), Var("y"), Var("z")


def f(e: Expr, name: str) -> Field:
    return Field(e, name)


def catalog(spark: SparkSession, sf_dir: str, *names: str) -> Catalog:
    cat = Catalog(spark)
    for name in names:
        cat.register(name, spark.read.parquet(f"{sf_dir}/{name}.parquet"), KEYS[name], TIES.get(name))
    return cat


def swap() -> Expr:
    """Lines with discount below tax as they are; the others with the two exchanged."""
    d, t = f(x, "l_discount"), f(x, "l_tax")
    keep = each("x", table("lineitem"), when(d < t, bag(rec(A=d, B=t, C=f(x, "l_quantity")))))
    other = each("x", table("lineitem"), when(op("not", d < t), bag(rec(A=t, B=d, C=f(x, "l_quantity")))))
    return union(keep, other)


def selection(quantity: int = 3) -> Expr:
    return select(table("lineitem"), lambda r: f(r, "l_quantity").eq(quantity), lambda r: rec(A=f(r, "l_partkey"), B=f(r, "l_extendedprice")))


def renaming() -> Expr:
    """The exchange inside the head: one record per line, whatever the condition says."""
    d, t = f(x, "l_discount"), f(x, "l_tax")
    low = op("if", d < t, d, t)
    high = op("if", d < t, t, d)
    return each("x", table("lineitem"), bag(rec(A=low, B=high, C=f(x, "l_quantity"))))


def projection_and_constant() -> Expr:
    return union(each("x", table("part"), bag(rec(B=f(x, "p_size")))), bag(rec(B=lit(3))))


def join() -> Expr:
    return query({"x": table("customer"), "y": table("supplier")}, rec(A=f(x, "c_acctbal"), B=f(y, "s_name")), f(x, "c_nationkey").eq(f(y, "s_nationkey")))


def large_join() -> Expr:
    return query({"x": table("lineitem"), "y": table("orders")}, rec(A=f(x, "l_partkey"), B=f(y, "o_orderpriority")), f(x, "l_orderkey").eq(f(y, "o_orderkey")))


def workflow_catalog(spark: SparkSession, sf_dir: str, n: int = 50) -> Catalog:
    """Part keys 1..n as two tables of scalars."""
    keys = spark.read.parquet(f"{sf_dir}/part.parquet").filter(F.col("p_partkey").between(1, n)).select(F.col("p_partkey").alias("value"), F.col("p_partkey").alias("_l0"))
    return Catalog(spark, {"T": keys, "U": keys})


def workflow() -> Expr:
    """Pairs x < y with a third element whose square is the sum of theirs; the result is the product."""
    return query({"x": table("T"), "y": table("T"), "z": table("U")}, x * y, (x < y) & (x * x + y * y).eq(z * z))


def document_copies() -> Expr:
    """A labelled good document, and a later one of equal text."""
    cond = op("hash", f(x, "text")).eq(op("hash", f(y, "text"))) & f(x, "text").eq(f(y, "text")) & (f(x, "doc_id") < f(y, "doc_id")) & f(z, "doc_id").eq(f(x, "doc_id")) & f(z, "quality").eq(1)
    return query({"x": table("documents"), "y": table("documents"), "z": table("labels")}, rec(n=f(x, "n_chars") + f(y, "n_chars")), cond)


def total(quantity: int = 3) -> Expr:
    return each("o", table("one"), bag(rec(total=Agg("sum", each("x", table("lineitem"), when(f(x, "l_quantity").eq(quantity), bag(rec(v=op("cents", f(x, "l_extendedprice"))))))))))


def one_catalog(spark: SparkSession, sf_dir: str, *names: str) -> Catalog:
    """A catalog with a table ``one`` of a single element, to which scalar queries attach."""
    cat = catalog(spark, sf_dir, *names)
    cat.tables["one"] = spark.range(1).select(F.lit(0).cast("long").alias("unit"), F.lit(0).cast("long").alias("_l0"))
    return cat


def without_orders(status: str = "F") -> Expr:
    """Customers without an order of a status."""
    return minus(table("customer"), table("orders"), lambda a, b: f(a, "c_custkey").eq(f(b, "o_custkey")) & f(b, "o_orderstatus").eq(status), lambda a: rec(A=f(a, "c_name")))


def customers_by_nation() -> Expr:
    return group_agg(table("nation"), table("customer"), lambda a, b: f(a, "n_nationkey").eq(f(b, "c_nationkey")), lambda a: {"name": f(a, "n_name")}, {"n": ("count", lambda b: f(b, "c_custkey")), "cents": ("sum", lambda b: op("cents", f(b, "c_acctbal")))})


def big_lines() -> Expr:
    """Large lines, named once, joined with their orders."""
    big = each("x", table("lineitem"), when(f(x, "l_quantity") > 49, bag(rec(k=f(x, "l_orderkey"), p=f(x, "l_partkey")))))
    b, o = Var("b"), Var("o")
    return let("big", big, query({"b": Var("big"), "o": table("orders")}, rec(p=f(b, "p"), s=f(o, "o_orderstatus")), f(b, "k").eq(f(o, "o_orderkey"))))


def nested_lines() -> Expr:
    """Customers, their orders, their lines: the flat form of three nested bags."""
    c, o, ln = Var("c"), Var("o"), Var("l")
    inner = each("l", table("lineitem"), when(f(ln, "l_orderkey").eq(f(o, "o_orderkey")), bag(rec(name=f(c, "c_name"), status=f(o, "o_orderstatus"), quantity=f(ln, "l_quantity")))))
    return each("c", table("customer"), each("o", table("orders"), when(f(o, "o_custkey").eq(f(c, "c_custkey")), inner)))


def sweep_catalog(spark: SparkSession, sf_dir: str) -> Catalog:
    cat = catalog(spark, sf_dir, "events")
    cat.tables["threshold"] = spark.createDataFrame([(50, 0), (100, 1), (200, 2), (400, 3)], "limit long, _l0 long")
    cat.tables["kind"] = spark.createDataFrame([(k, i) for i, k in enumerate(["purchase", "click", "view", "signup", "logout"])], "event_type string, _l0 long")
    return cat


def sweep() -> Expr:
    """Events of a type above a threshold, counted for every pair of the two."""
    t, k, e = Var("t"), Var("k"), Var("e")
    n = Agg("count", each("e", table("above"), when(f(e, "event_type").eq(f(k, "event_type")) & f(e, "limit").eq(f(t, "limit")), bag(rec(v=lit(1))))))
    return each("t", table("threshold"), each("k", table("kind"), bag(rec(limit=f(t, "limit"), event_type=f(k, "event_type"), n=n))))


def with_above(cat: Catalog) -> Catalog:
    """Events beside each threshold that they exceed, as a table of its own (labels: event, threshold)."""
    events = cat["events"].select("event_id", "event_type", "value")
    bounds = F.array(*[F.struct(F.lit(b).cast("long").alias("limit"), F.lit(i).cast("long").alias("i")) for i, b in enumerate((50, 100, 200, 400))])
    spread = events.select("event_id", "event_type", "value", F.explode(F.filter(bounds, lambda b: F.col("value") > b["limit"])).alias("b"))
    rows = spread.select("event_type", F.col("b.limit").alias("limit"), F.col("event_id").cast("long").alias("_l0"), F.col("b.i").alias("_l1"))
    return cat.replaced("above", rows)


dot = primitive("dot", lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v), "number")


def near_vectors(least: float = 0.25, product=dot) -> Expr:
    """Pairs of one label whose vectors' product, an opaque step, exceeds a threshold."""
    cond = f(x, "label").eq(f(y, "label")) & (f(x, "vec_id") < f(y, "vec_id")) & (product(f(x, "embedding"), f(y, "embedding")) > least)
    return query({"x": table("embeddings"), "y": table("embeddings")}, rec(label=f(x, "label")), cond)


host = primitive("host", lambda u: F.regexp_extract(u, "^https?://([^/]+)", 1), "string")
title_length = primitive("title_length", lambda h: F.length(F.regexp_extract(h, "<title>([^<]*)</title>", 1)), "number")


def pages_of_a_host() -> Expr:
    cond = host(f(x, "url")).eq(host(f(y, "url"))) & (f(x, "page_id") < f(y, "page_id"))
    return query({"x": table("pages"), "y": table("pages")}, rec(host=host(f(x, "url")), n=title_length(f(x, "html")) + title_length(f(y, "html"))), cond)


def part_sizes() -> Expr:
    return rename(table("part"), {"size": "p_size"})


def region_pairs() -> Expr:
    """Nations that share a region with another or themselves: values with several witnesses, some within others."""
    return query({"x": table("nation"), "y": table("nation")}, rec(region=f(x, "n_regionkey")), f(x, "n_regionkey").eq(f(y, "n_regionkey")))


def nested_frame(cat: Catalog) -> DataFrame:
    """Customers with a bag of orders, each with a bag of lines, assembled from child frames keyed by the parents' labels."""
    lines = cat["lineitem"].select("l_orderkey", F.struct(F.concat_ws(".", "_l1", "_l2").alias("lbl"), "l_quantity").alias("line"))
    orders = lines.groupBy("l_orderkey").agg(F.sort_array(F.collect_list("line")).alias("lines"))
    of = cat["orders"].join(orders, F.col("o_orderkey") == F.col("l_orderkey"), "left").select("o_custkey", F.struct(F.col("_l0").alias("lbl"), "o_orderstatus", F.coalesce("lines", F.array()).alias("lines")).alias("order"))
    grouped = of.groupBy("o_custkey").agg(F.sort_array(F.collect_list(F.struct("order.lbl", "order"))).alias("orders"))
    return cat["customer"].join(grouped, F.col("c_custkey") == F.col("o_custkey"), "left").select(F.col("_l0").cast("string").alias("lbl"), "c_name", F.coalesce(F.transform("orders", lambda o: o["order"]), F.array()).alias("orders"))


def unnested(nested: DataFrame) -> DataFrame:
    """A nested frame's lines with the labels of all levels in front: a nested bag used as a generator."""
    orders = nested.select("lbl", "c_name", F.explode("orders").alias("o"))
    lines = orders.select(F.col("lbl").alias("c"), "c_name", F.col("o.lbl").alias("o"), F.col("o.o_orderstatus").alias("status"), F.explode("o.lines").alias("l"))
    return lines.select(F.concat_ws(".", "c", "o", "l.lbl").alias("lbl"), F.col("c_name").alias("name"), "status", F.col("l.l_quantity").alias("quantity"))




# --- nested results ----------------------------------------------------------------------------------------------------


def nested_customers() -> Expr:
    """Customers with a bag of their orders, each with a bag of its lines."""
    c, o, ln = Var("c"), Var("o"), Var("l")
    lines = each("l", table("lineitem"), when(f(ln, "l_orderkey").eq(f(o, "o_orderkey")), bag(rec(quantity=f(ln, "l_quantity")))))
    orders = each("o", table("orders"), when(f(o, "o_custkey").eq(f(c, "c_custkey")), bag(rec(status=f(o, "o_orderstatus"), lines=lines))))
    return each("c", table("customer"), bag(rec(name=f(c, "c_name"), orders=orders)))


def talks_catalog(spark: SparkSession, sf_dir: str) -> Catalog:
    """Conversations' turns, and their ids as a table of its own."""
    cat = catalog(spark, sf_dir, "conversations")
    return cat.register("talks", spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id").distinct(), ["conv_id"])


def talks() -> Expr:
    """Conversations with a bag of their turns."""
    v, t = Var("v"), Var("t")
    turns = each("t", table("conversations"), when(f(t, "conv_id").eq(f(v, "conv_id")), bag(rec(turn=f(t, "turn"), role=f(t, "role")))))
    return each("v", table("talks"), bag(rec(conv=f(v, "conv_id"), turns=turns)))


# --- further queries ---------------------------------------------------------------------------------------------------


def exchange() -> Expr:
    """The exchange by a conditional whose branches are whole records: what a trace records of it can flip."""
    d, t = f(x, "l_discount"), f(x, "l_tax")
    return each("x", table("lineitem"), when(d < t, bag(rec(A=d, B=t, C=f(x, "l_quantity"))), bag(rec(A=t, B=d, C=f(x, "l_quantity")))))


def balances_by_nation() -> Expr:
    """Largest, smallest and mean balance of a nation's customers."""
    value = lambda b: op("cents", f(b, "c_acctbal"))
    return group_agg(table("nation"), table("customer"), lambda a, b: f(a, "n_nationkey").eq(f(b, "c_nationkey")), lambda a: {"name": f(a, "n_name")}, {"most": ("max", value), "least": ("min", value), "mean": ("avg", value)})


def balances_below() -> Expr:
    """Balances of all customers of nations with a smaller key: an aggregate that correlates by an order."""
    inner = each("y", table("customer"), when(f(y, "c_nationkey") < f(x, "n_nationkey"), bag(rec(v=op("cents", f(y, "c_acctbal"))))))
    return each("x", table("nation"), bag(rec(name=f(x, "n_name"), cents=Agg("sum", inner))))


def nations_without() -> Expr:
    """Nations, and whether none of their customers is in debt: an emptiness test in a head."""
    debt = each("y", table("customer"), when(f(y, "c_nationkey").eq(f(x, "n_nationkey")) & (f(y, "c_acctbal") < 0), bag(rec(one=lit(1)))))
    return each("x", table("nation"), bag(rec(name=f(x, "n_name"), clear=IsEmpty(debt))))


def rich_without_orders(status: str = "F") -> Expr:
    """Customers with a positive balance and no order of a status: an emptiness test inside a conjunction."""
    none = IsEmpty(each("y", table("orders"), when(f(y, "o_custkey").eq(f(x, "c_custkey")) & f(y, "o_orderstatus").eq(status), bag(rec(one=lit(1))))))
    return each("x", table("customer"), when((f(x, "c_acctbal") > 0) & none, bag(rec(A=f(x, "c_name")))))


def customers_and_suppliers() -> Expr:
    """Customers with the suppliers of their nation that have a high balance; those without any, too."""
    on = lambda a, b: f(a, "c_nationkey").eq(f(b, "s_nationkey")) & (f(b, "s_acctbal") > 8000)
    return outer(table("customer"), table("supplier"), on, lambda a, b: {"A": f(a, "c_name"), "B": f(b, "s_name")}, lambda a: {"A": f(a, "c_name")})


def customer_groupings() -> Expr:
    """Customers counted by nation, by region, and in all."""
    by_nation = (table("nation"), lambda a, b: f(a, "n_nationkey").eq(f(b, "c_nationkey")), lambda a: {"nation": f(a, "n_nationkey")})
    by_sign = (table("sign"), lambda a, b: f(a, "negative").eq(f(b, "c_acctbal") < 0), lambda a: {"negative": f(a, "negative")})
    overall = (table("one"), lambda a, b: f(a, "unit").eq(0), lambda a: {})
    return grouping_sets(table("customer"), [by_nation, by_sign, overall], {"n": ("count", lambda b: f(b, "c_custkey"))})


def groupings_catalog(spark: SparkSession, sf_dir: str) -> Catalog:
    cat = one_catalog(spark, sf_dir, "nation", "customer")
    cat.tables["sign"] = spark.createDataFrame([(False, 0), (True, 1)], "negative boolean, _l0 long")
    return cat
