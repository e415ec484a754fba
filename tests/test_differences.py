"""Differences of results and checks over few labels, beside plain evaluations that list everything."""

import pytest
from pyspark.sql import functions as F

from backtrail import workloads as w
from backtrail.operators import checks, differences
from backtrail.operators.runs import reached, trace
from backtrail.operators.slicing import Target, first_labels, slice_inputs
from backtrail.plans import compile as plan
from backtrail.sources.catalog import Catalog

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def cat(spark):
    return w.catalog(spark, SMALL, "customer", "supplier")


def moved(cat):
    """Nations of some suppliers change, some customers go, balances of others change, new suppliers come."""
    supplier = cat["supplier"].withColumn("s_nationkey", F.when(F.col("s_suppkey") % 4 == 0, (F.col("s_nationkey") + 1) % 25).otherwise(F.col("s_nationkey")))
    new = cat["supplier"].filter("s_suppkey % 5 = 0").withColumn("_l0", F.col("_l0") + 1000)
    customer = cat["customer"].filter("c_custkey % 7 <> 0").withColumn("c_acctbal", F.when(F.col("c_custkey") % 3 == 0, F.lit(None)).otherwise(F.col("c_acctbal")))
    return cat.replaced("supplier", supplier.unionByName(new)).replaced("customer", customer)


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_differences_are_those_of_listed_results(cat):
    run, other = trace(w.join(), cat), moved(cat)
    a, b = run.value(), trace(w.join(), other).value()
    assert rows(differences.labels(run.blocks, cat, other)) == rows(a.select("lbl").join(b, "lbl", "left_anti")) != []
    assert rows(differences.labels(run.blocks, other, cat)) == rows(b.select("lbl").join(a, "lbl", "left_anti")) != []
    changed = a.exceptAll(b).unionByName(b.exceptAll(a)).select("lbl").distinct()
    assert rows(differences.rows(run.blocks, cat, other)) == rows(changed)
    assert rows(differences.rows(run.blocks, cat, cat)) == []


def test_checks_find_what_is_wrong(cat):
    run, other = trace(w.join(), cat), moved(cat)
    target = Target.cells(run, {lbl: ["A"] for lbl in first_labels(run, 3)}).closed()
    plain = Target(run, target.frames, target.rest)
    assert rows(checks.target_violations(run, target, other)) == rows(checks.target_violations(run, plain, other)) != []
    struck = checks.slice_violations(run, target, strike=("supplier", "s_nationkey"))
    assert {r["reason"] for r in struck.collect()} == {"missing", "unlisted"}


@pytest.mark.parametrize("by_number", [True, False])
def test_first_labels(spark, cat, by_number):
    run = trace(w.join(), cat)
    key = (lambda x: [int(p) for p in x.split(".")]) if by_number else None
    assert first_labels(run, 30, by_number) == sorted([r["lbl"] for r in run.value().collect()], key=key)[:30]
    lines = w.catalog(spark, SMALL, "lineitem", "orders", "customer")
    for query in (w.swap(), w.big_lines(), w.nested_lines()):
        run = trace(query, lines)
        assert first_labels(run, 4, by_number) == sorted([r["lbl"] for r in run.value().collect()], key=key)[:4]


def test_reached_elements_and_counts(spark):
    """Chains, guards of one element, and generators that only a third connects."""
    numbers = Catalog.of_rows(spark, T=(["value"], {(i,): (i,) for i in range(1, 21)}), U=(["value"], {(i,): (i,) for i in range(1, 21)}))
    lines = w.catalog(spark, SMALL, "lineitem", "orders", "customer")
    for query, cat in ((w.workflow(), numbers), (w.nested_lines(), lines), (w.big_lines(), lines)):
        for block in trace(query, cat).blocks:
            whole = plan.frame(block, cat)
            assert plan.frame_count(block, cat) == whole.count()
            for gen in block.gens:
                labels = plan.gen_labels(cat, gen)
                assert rows(reached(block, cat, len(block.steps), gen)) == rows(whole.select(*labels).distinct())


def test_target_of_few_labels_reads_few_rows(spark, cat):
    """The elements asked for come from the elements their labels name: no row of the whole join is made."""
    run = trace(w.join(), cat)
    first = first_labels(run, 1)[0]
    target = Target.cells(run, {first: ["A"]})
    plans = target.frames[0]._jdf.queryExecution().optimizedPlan().toString()
    assert "IN" in plans or "_l0" in plans and first.split(".")[0] in plans
    assert rows(slice_inputs(run, target)["customer"].rows.select("_l0")) == [(int(first.split(".")[0]),)]
    assert rows(target.closed().asked[0].select(plan.gen_labels(cat, run.blocks[0].gens[0])[0])) == [(int(first.split(".")[0]),)]


def test_filled_holes_do_not_multiply_other_elements(spark):
    """Keys altered outside the slice meet one another by the thousand; only the target's own element is computed again."""
    let = trace(w.big_lines(), w.catalog(spark, SMALL, "lineitem", "orders"))
    target = Target.cells(let, {first_labels(let)[0]: ["s"]})
    changed = checks.perturbed(let.cat, slice_inputs(let, target))
    assert trace(w.big_lines(), changed).value().count() > 20 * let.value().count()
    found = checks.target_violations(let, target, changed)
    assert found.count() == 0
    assert "IN" in found._jdf.queryExecution().optimizedPlan().toString() or "Filter" in found._jdf.queryExecution().optimizedPlan().toString()


def test_slice_of_an_outer_join_without_lone_elements(spark, tmp_path):
    """Where every customer has a partner, the query says what its SQL says."""
    from backtrail.deep_queries import QUERIES, SQL
    import duckdb

    spark.read.parquet(f"{SMALL}/customer.parquet").write.parquet(str(tmp_path / "customer.parquet"))
    spark.range(25).select(F.col("id").alias("s_suppkey"), F.lit("s").alias("s_name"), F.col("id").cast("int").alias("s_nationkey"), F.lit(9000.0).alias("s_acctbal")).write.parquet(str(tmp_path / "supplier.parquet"))
    con = duckdb.connect()
    for name in ("customer", "supplier"):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{tmp_path}/{name}.parquet/*.parquet'")
    expected = sorted(map(repr, con.execute(SQL["slice_outer"]).fetchall()))
    found = QUERIES["slice_outer"](spark, str(tmp_path)).select("source_table", "lbl", "column").collect()
    assert sorted(repr(tuple(r)) for r in found) == expected != []


def test_differences_of_one_generator(spark):
    """Elements that go, come, change or change branch; a plan without a second reading for groups."""
    cat = w.catalog(spark, SMALL, "lineitem")
    new = cat["lineitem"].filter("l_orderkey < 9").withColumn("_l0", F.col("_l0") + 10_000_000)
    changed = cat["lineitem"].filter("l_orderkey % 5 <> 0").withColumn("l_quantity", F.when(F.col("l_orderkey") % 3 == 0, F.lit(3.0)).otherwise(F.col("l_quantity")))
    other = cat.replaced("lineitem", changed.withColumn("l_extendedprice", F.when(F.col("l_orderkey") % 2 == 0, F.lit(None)).otherwise(F.col("l_extendedprice"))).unionByName(new))
    run = trace(w.selection(), cat)
    a, b = run.value(), trace(w.selection(), other).value()
    assert rows(differences.rows(run.blocks, cat, other)) == rows(a.exceptAll(b).unionByName(b.exceptAll(a)).select("lbl").distinct()) != []
    assert rows(differences.labels(run.blocks, cat, other)) == rows(a.select("lbl").join(b, "lbl", "left_anti")) != []
    found = differences.rows(run.blocks, cat, other)._jdf.queryExecution().optimizedPlan().toString()
    assert found.count("Relation [") <= 3
