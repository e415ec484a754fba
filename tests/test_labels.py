"""Labels: prefix codes, sub-codes, edits that never relabel."""

from pyspark.sql import functions as F

from backtrail import workloads as w
from backtrail.operators.runs import evaluate, trace, trace_rows
from backtrail.sources.catalog import Catalog, Edits, fresh_labels, hashed_labels, prefix_disjoint_violations, prefix_violations, sub_code_violations

SMALL = "/root/testdata/sf0.001"


def labels(spark, *given):
    return spark.createDataFrame([(list(g),) for g in given], "label array<bigint>")


def test_violations(spark):
    assert prefix_violations(labels(spark, (1, 1), (1, 2), (2,))).count() == 0
    assert {(tuple(r["label"]), r["reason"]) for r in prefix_violations(labels(spark, (1,), (1, 2), (3,), (3,))).collect()} == {((1,), "prefix"), ((3,), "repeated")}
    assert sub_code_violations(labels(spark, (1, 5), (2,)), labels(spark, (1,), (2,))).count() == 0
    assert [tuple(r["label"]) for r in sub_code_violations(labels(spark, (1, 5), (4,)), labels(spark, (1,))).collect()] == [(4,)]
    assert prefix_disjoint_violations(labels(spark, (1,)), labels(spark, (2,))).count() == 0
    assert prefix_disjoint_violations(labels(spark, (1,)), labels(spark, (1, 2))).count() == 1


def test_every_source_and_result_is_a_prefix_code(spark):
    cat = Catalog.of_folder(spark, SMALL)
    for name in cat.tables:
        keys = cat.labels(name)
        assert prefix_violations(cat[name].select(F.array(*keys).alias("label"))).count() == 0, name
    queries = {"swap": w.swap(), "join": w.join(), "const": w.projection_and_constant(), "let": w.big_lines(), "nested": w.nested_lines()}
    for name, q in queries.items():
        found = evaluate(q, cat).select(F.split("lbl", r"\.").cast("array<bigint>").alias("label"))
        assert prefix_violations(found).count() == 0, name


def test_edits_keep_labels(spark):
    cat = Catalog.of_folder(spark, SMALL, ["lineitem"])
    first = cat["lineitem"].orderBy("_l0", "_l1", "_l2").first()
    at = (first["_l0"], first["_l1"], first["_l2"])
    changed = cat.apply(Edits("lineitem").update(at, "l_quantity", 1.5).update(at, "l_returnflag", None).insert((10**9, 1, 1), l_quantity=2.0).add_field("note", "x"))
    rows = changed["lineitem"]
    assert rows.count() == cat["lineitem"].count() + 1
    hit = rows.filter((F.col("_l0") == at[0]) & (F.col("_l1") == at[1]) & (F.col("_l2") == at[2])).collect()
    assert len(hit) == 1 and hit[0]["l_quantity"] == 1.5 and hit[0]["l_returnflag"] is None and hit[0]["note"] == "x"
    assert cat.apply(Edits("lineitem").delete(at))["lineitem"].count() == cat["lineitem"].count() - 1
    assert "l_tax" not in cat.apply(Edits("lineitem").drop_field("l_tax"))["lineitem"].columns


def test_labels_without_keys(spark):
    df = spark.createDataFrame([("a",), ("a",), ("b",)], "v string")
    again = [hashed_labels(df.repartition(n)).select("_l0", "_l1", "v").orderBy("_l0", "_l1").collect() for n in (1, 3)]
    assert again[0] == again[1] and len({(r["_l0"], r["_l1"]) for r in again[0]}) == 3
    fresh = [tuple(r[0] for r in fresh_labels(df).select("_l0").collect()) for _ in range(2)]
    assert fresh[0] != fresh[1]


def test_trace_modes_agree(spark, tmp_path):
    cat = Catalog.of_folder(spark, SMALL, ["customer", "supplier"])
    runs = [trace(w.join(), cat), trace(w.join(), cat, "lazy"), trace(w.join(), cat, "eager", "taken", str(tmp_path / "t")), trace(w.join(), cat, "eager", "full")]
    counts = [trace_rows(r).filter("branch").count() for r in runs]
    assert len(set(counts)) == 1 and counts[0] == evaluate(w.join(), cat).count()
    assert trace_rows(runs[3]).count() == cat["customer"].count() * cat["supplier"].count()
    try:
        trace(w.join(), cat, "lazy", "full", limit=10)
        raise AssertionError("a full trace beyond the limit must be refused")
    except ValueError:
        pass


def test_full_traces_of_products_are_described_over_what_was_written(spark):
    """A product of any size is traced in full; what was written stands for tables that change afterwards."""
    from backtrail.operators.runs import is_subtrace, trace_rows
    from backtrail.operators.slicing import Target, first_labels, slice_inputs, slice_trace, sliced_trace

    cat = w.catalog(spark, "/root/testdata/sf0.001", "customer", "supplier")
    many = Catalog(spark, {t: df.withColumn("_n", F.explode(F.sequence(F.lit(0), F.lit(199)))).withColumn("_l0", F.col("_l0") + 1000 * F.col("_n")).drop("_n") for t, df in cat.tables.items()})
    assert many["customer"].count() * many["supplier"].count() > 50_000_000
    for mode in ("lazy", "eager"):
        run = trace(w.join(), many, mode, "full")
        target = Target.cells(run, {first_labels(run)[0]: ["A"]})
        part = sliced_trace(slice_trace(run, target))
        assert part.count() == 1 and is_subtrace(part, trace_rows(run, "full", among=part)).count() == 0
        assert is_subtrace(part, sliced_trace(slice_trace(run, target.closed()), among=part)).count() == 0
    small = trace(w.join(), Catalog(spark, dict(cat.tables)), "eager", "full")
    listed = sorted(map(tuple, trace_rows(small, "full").collect()))
    assert len(listed) == cat["customer"].count() * cat["supplier"].count()
    assert listed == sorted(map(tuple, trace_rows(trace(w.join(), cat), "full").collect()))
    before = {t: sorted(map(tuple, d.labelled().collect())) for t, d in slice_inputs(small, Target.cells(small, {first_labels(small)[0]: ["A"]}).closed()).items()}
    small.cat.tables["supplier"] = cat["supplier"].withColumn("s_nationkey", F.lit(99))
    after = {t: sorted(map(tuple, d.labelled().collect())) for t, d in slice_inputs(small, Target.cells(small, {first_labels(small)[0]: ["A"]}).closed()).items()}
    assert before == after and sorted(map(tuple, trace_rows(small, "full").collect())) == listed


def test_sub_codes_of_several_lengths(spark):
    inner, outer = labels(spark, (1, 5), (2,), (3, 4, 5), (7,), (3,)), labels(spark, (1,), (2,), (3, 4))
    assert sorted(tuple(r["label"]) for r in sub_code_violations(inner, outer).collect()) == [(3,), (7,)]
    plans = sub_code_violations(inner, outer)._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plans  # no label is spread over its beginnings
