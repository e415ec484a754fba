"""Provenance read off labels: no comparison of pairs where labels tell them apart, the same rows where they do not."""

from pyspark.sql import functions as F

from backtrail import queries, workloads as w
from backtrail.operators import provenance
from backtrail.operators.runs import trace

SMALL = "/root/testdata/sf0.001"


def aggregates(df):
    return df._jdf.queryExecution().optimizedPlan().toString().count("Aggregate")


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_labels_that_tell_pairs_apart_need_no_distinct(spark):
    run = trace(w.join(), w.catalog(spark, SMALL, "customer", "supplier"))
    assert provenance.labels_tell(run)
    for made in (provenance.lineage(run), provenance.export_graph(run)):
        assert aggregates(made) == 0 and rows(made) == rows(made.distinct())
    gone = run.cat["supplier"].filter("s_suppkey % 2 = 0").select(F.col("_l0").cast("string").alias("source"))
    left = provenance.how_delete(run, "supplier", gone)
    assert rows(left) == sorted((r["lbl"],) for r in run.value().collect() if int(r["lbl"].split(".")[1]) % 2)


def test_repeated_or_absent_labels_are_still_compared(spark):
    cat = w.catalog(spark, SMALL, "customer", "supplier")
    twice = cat.replaced("supplier", cat["supplier"].unionAll(cat["supplier"]))
    absent = cat.replaced("supplier", cat["supplier"].withColumn("_l0", F.when(F.col("_l0") > 1, F.col("_l0"))))
    for other in (twice, absent):
        run = trace(w.join(), other)
        assert not provenance.labels_tell(run)
        made = rows(provenance.lineage(run))
        assert len(made) == len(set(made))
    assert rows(provenance.lineage(trace(w.join(), twice))) == rows(provenance.lineage(trace(w.join(), cat)))


def spread_over_tasks(df):
    tasks = df.groupBy(F.spark_partition_id().alias("t")).count().collect()
    return len(tasks) > 1 and max(r["count"] for r in tasks) < 0.5 * sum(r["count"] for r in tasks)


def above_the_join(df):
    text = df._jdf.queryExecution().optimizedPlan().toString()
    return text[: text.index("Join")]


def test_lineage_puts_labels_together_in_several_tasks(spark):
    """Labels become text once an element, before the join; a small file's pairs are not left to one task."""
    made = queries.QUERIES["lineage_join"](spark, "/root/testdata/sf0.1")
    assert spread_over_tasks(made)
    assert "cast(" not in above_the_join(made)


def test_lineage_of_other_runs_is_the_same(spark):
    """A run with a written result, one block over one table, and a union's branches, which are compared."""
    cat = w.catalog(spark, SMALL, "customer", "supplier", "lineitem", "part")
    for query in (w.join(), w.selection(), w.projection_and_constant()):
        made = [rows(provenance.lineage(trace(query, cat, mode))) for mode in ("on_demand", "lazy", "eager")]
        assert made[0] and made[0] == made[1] == made[2]
    assert rows(provenance.lineage(trace(w.selection(), cat))) == sorted((r["lbl"], "lineitem", r["lbl"]) for r in trace(w.selection(), cat).value().collect())


def test_what_survives_is_looked_up_once_an_element_in_several_tasks(spark):
    made = queries.QUERIES["how_delete_join"](spark, "/root/testdata/sf0.1")
    assert spread_over_tasks(made)
    assert "cast(" not in above_the_join(made) and "LeftAnti" not in above_the_join(made)


def test_what_survives_in_other_runs(spark):
    """Elements of either table, none, and all; written results; several elements of one table, which are compared."""
    cat = w.catalog(spark, SMALL, "customer", "supplier", "nation")
    named = lambda df: df.select(F.col("_l0").cast("string").alias("source"))
    for mode in ("on_demand", "eager"):
        run = trace(w.join(), cat, mode)
        whole = rows(run.value().select("lbl"))
        for table, place in (("customer", 0), ("supplier", 1)):
            for cond in ("_l0 % 3 = 0", "false", "true"):
                gone = {r["source"] for r in named(cat[table].filter(cond)).collect()}
                left = provenance.how_delete(run, table, named(cat[table].filter(cond)))
                assert rows(left) == [r for r in whole if r[0].split(".")[place] not in gone], (mode, table, cond)
        assert rows(provenance.how_delete(run, "nation", named(cat["nation"]))) == whole
    run = trace(w.region_pairs(), cat)
    left = provenance.how_delete(run, "nation", named(cat["nation"].filter("_l0 % 2 = 0")))
    assert rows(left) == [r for r in rows(run.value().select("lbl")) if all(int(x) % 2 for x in r[0].split("."))]


def test_graph_is_put_together_in_several_tasks(spark):
    made = queries.QUERIES["graph_join"](spark, "/root/testdata/sf0.1")
    assert spread_over_tasks(made)
    assert "cast(" not in above_the_join(made)


def test_graph_of_other_runs_is_the_same(spark):
    """Written results, one table, and a union's branches, which are compared."""
    cat = w.catalog(spark, SMALL, "customer", "supplier", "lineitem", "part")
    for query in (w.join(), w.selection(), w.projection_and_constant()):
        made = [rows(provenance.export_graph(trace(query, cat, mode))) for mode in ("on_demand", "eager")]
        assert made[0] and made[0] == made[1]
    labels = [r["lbl"] for r in trace(w.selection(), cat).value().collect()]
    expected = [(f"result:{x}", "generated_by", f"step0:{x}") for x in labels] + [(f"step0:{x}", "used", f"lineitem:{x}") for x in labels]
    assert rows(provenance.export_graph(trace(w.selection(), cat))) == sorted(expected)
