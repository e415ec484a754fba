"""Joins beside plain versions."""

from collections import Counter

from pyspark.sql import functions as F

from backtrail.operators import joins
from backtrail.operators.runs import trace_rows
from backtrail import queries, surface_queries, workloads as w
from backtrail.plans import compile as plan
from backtrail.plans.blocks import flatten, used


def test_contains_join_of_many_items(spark):
    """Both branches beside contains(): short items, items inside words or after a quote, blanks, repeats, nulls."""
    texts = [(1, 'he said "the quick brown fox jumps over" it'), (2, "xthe quick brown fox jumps over the lazy dog"), (3, "fox"), (4, ""), (5, None), (1, 'he said "the quick brown fox jumps over" it')]
    items = ["the quick brown fox jumps over", "quick brown fox jumps over the lazy dog", "fox", "o", "", None, "fox", "brown  fox", "ox jumps over the lazy dogs", "he said \"the quick brown f"]
    left = spark.createDataFrame(texts, "doc long, text string")
    right = spark.createDataFrame(list(enumerate(items)), "nr int, item string")
    expected = Counter((d, n) for d, t in texts for n, i in enumerate(items) if t is not None and i is not None and i in t)
    for most in (100, 2):
        found = joins.contains_join(left, right, "text", "item", most=most).select("doc", "nr").collect()
        assert Counter(map(tuple, found)) == expected, most
    assert joins.contains_join(left, right.withColumn("item", F.concat("item", F.lit("#"))), "text", "item", most=2).count() == 0


def test_contains_join_in_long_texts(spark):
    """Items at every place of a text of several stretches, across their borders too; a long text takes time in proportion."""
    import time

    words = "".join(chr(97 + (i * i * 7 + i // 26) % 26) for i in range(1500)) + "é𝄞ü"
    items = [words[i : i + n] for i in range(0, 1503, 13) for n in (5, 24, 31)] + [words[250:290], words[-3:]]
    left = spark.createDataFrame([(1, words), (2, words[::-1])], "doc long, text string")
    right = spark.createDataFrame(list(enumerate(items)), "nr int, item string")
    expected = Counter((d, n) for d, t in ((1, words), (2, words[::-1])) for n, i in enumerate(items) if i in t)
    assert Counter(map(tuple, joins.contains_join(left, right, "text", "item", most=2).select("doc", "nr").collect())) == expected
    long = spark.createDataFrame([(1, "xyz " * 100_000 + "the needle")], "doc long, text string")
    needles = spark.createDataFrame([(0, "the needle"), (1, "a needle"), (2, "yz xyz")], "nr int, item string")
    start = time.time()
    assert sorted(r[0] for r in joins.contains_join(long, needles, "text", "item", most=1).select("nr").collect()) == [0, 2]
    assert time.time() - start < 60


def test_full_join_covers_both_tables(spark):
    from backtrail.surface_queries import QUERIES

    d = "/root/testdata/sf0.01"
    rows = QUERIES["surface_full_join"](spark, d).collect()
    assert len({r["c_custkey"] for r in rows} - {None}) == spark.read.parquet(f"{d}/customer.parquet").count()
    assert len({r["s_suppkey"] for r in rows} - {None}) == spark.read.parquet(f"{d}/supplier.parquet").count()
    assert any(r["c_custkey"] is None for r in rows) and any(r["s_suppkey"] is None for r in rows)


def test_interval_join_covers_all_parts(spark):
    from backtrail.surface_queries import QUERIES

    d = "/root/testdata/sf0.01"
    assert QUERIES["surface_interval_join"](spark, d).count() == spark.read.parquet(f"{d}/part.parquet").count()


def test_opaque_steps_are_applied_before_the_join(spark):
    """Pages of a host: hosts and title lengths once a page, and no page's text in the join."""
    cat = w.catalog(spark, "/root/testdata/sf0.001", "pages")
    block, tables = plan.beforehand(flatten(w.pages_of_a_host(), cat.columns)[0], cat)
    assert not {c for e in (block.head, *(g.cond for g in block.guards)) for _, c in used(e)} & {"html", "url"}
    assert all("html" not in tables.columns(g.table) and tables.labels(g.table) == ["_l0"] for g in block.gens)
    assert all(tables[g.table].count() == cat["pages"].count() for g in block.gens)
    text = plan.value(flatten(w.pages_of_a_host(), cat.columns)[0], cat)._jdf.queryExecution().optimizedPlan().toString()
    assert "regexp_extract" not in text[: text.index("Join")]


def test_pairs_of_a_small_file_are_spread_over_tasks(spark):
    """One task reads the customers; what they are joined to is listed by several."""
    cat = w.catalog(spark, "/root/testdata/sf0.1", "customer", "supplier")
    spread = cat.spread("customer")
    assert cat["customer"].rdd.getNumPartitions() == 1
    assert spread.labels("customer") == cat.labels("customer") and spread["customer"].exceptAll(cat["customer"]).count() == 0
    for name in ("eval_join",):
        tasks = queries.QUERIES[name](spark, "/root/testdata/sf0.1").select(F.spark_partition_id().alias("t")).groupBy("t").count().collect()
        assert len(tasks) > 1 and max(r["count"] for r in tasks) < 0.5 * sum(r["count"] for r in tasks)


def test_a_written_trace_is_listed_by_several_tasks(spark, monkeypatch):
    runs, real = [], surface_queries.io.write_trace
    monkeypatch.setattr(surface_queries.io, "write_trace", lambda run, *where: runs.append(run) or real(run, *where))
    found = surface_queries.QUERIES["io_trace"](spark, "/root/testdata/sf0.1").collect()
    tasks = trace_rows(runs[0]).groupBy(F.spark_partition_id().alias("t")).count().collect()
    assert len(tasks) > 1 and sum(r["count"] for r in tasks) == found[0]["n"]


def test_pieces_beside_plain_search(monkeypatch):
    """Pieces of all lengths, prefixes of each other, of several bytes a character, across the borders of blocks and of rows."""
    import pickle
    import random

    import pyarrow as pa

    from backtrail.functions import pieces

    draw = random.Random(5)
    texts = ["".join(draw.choices("abé𝄞 ", k=draw.choice([0, 1, 3, 40, 300]))) for _ in range(60)] + [None, "a" * 500, "", "zq", "b"]
    items = {"".join(draw.choices("abé𝄞 ", k=n)) for n in range(1, 6) for _ in range(30)} | {t[i : i + n] for t in texts if t for n in (2, 7, 8, 9, 15, 16, 17, 31, 33, 70, 290) for i in (0, 5) if t[i : i + n]}
    items = sorted(items | {"absent", "a" * 499, "a" * 501, "bzq", "aa" + "b"})
    expected = [(r, n) for r, t in enumerate(texts) for n, i in enumerate(items) if t and i in t]
    for block in (pieces.BLOCK, 64, 7):
        monkeypatch.setattr(pieces, "BLOCK", block)
        known = pickle.loads(pickle.dumps(pieces.Pieces(pa.array(items))))
        for array in (pa.array(texts), pa.array(["a", *texts, "a"], pa.large_string()).slice(1, len(texts))):
            row, piece = known.within(array)
            assert list(zip(row.tolist(), piece.tolist())) == expected, block
    row, piece = pieces.Pieces(pa.array(["a"])).within(pa.array([None, ""], pa.string()))
    assert len(row) == len(piece) == 0


def test_pieces_of_one_hash_are_told_apart():
    """A hash never decides alone: with all codes equal, every window of a length has one hash."""
    import numpy as np
    import pyarrow as pa

    from backtrail.functions import pieces

    known = pieces.Pieces(pa.array(["abc"])).ready()
    known.sums.codes = np.zeros(256, np.uint64)
    known.whole, known.begins = np.full(1, 3, np.uint64) * pieces._LENGTH, {3: (np.zeros(1, np.uint64), *known.begins[3][1:])}
    known.marks = {3: (np.ones(1 << 16, bool), np.uint64(48))}
    row, piece = known.within(pa.array(["xxabx", "xxabcx", "acbabc"]))
    assert row.tolist() == [1, 2] and piece.tolist() == [0, 0]


def test_contains_join_streams_texts_in_passes(spark):
    """Many items: texts are not searched item by item nor shuffled, and items beyond one pass take more passes, not fewer items."""
    texts = [(i, f"{'lorem ipsum ' * (i % 5)}item{i * 3}. and item{i}") for i in range(60)] + [(60, None), (3, "again item3")]
    items = [f"item{i}" for i in range(40)] + ["item7", None, "", "and item1"]
    left = spark.createDataFrame(texts, "doc long, text string")
    right = spark.createDataFrame(list(enumerate(items)), "nr int, item string")
    expected = Counter((d, n) for d, t in texts for n, i in enumerate(items) if t is not None and i is not None and i in t)
    for at_once in ((joins.HASHES, joins.PIECES), (10, joins.PIECES), (joins.HASHES, 50)):
        found = joins.contains_join(left, right, "text", "item", most=2, at_once=at_once)
        assert Counter(map(tuple, found.select("doc", "nr").collect())) == expected, at_once
        assert "Contains(" not in found._jdf.queryExecution().optimizedPlan().toString()


def test_contamination_reads_texts_once(spark):
    from backtrail import deep_queries

    made = deep_queries.QUERIES["eval_contamination_many"](spark, "/root/testdata/sf0.001")
    text = made._jdf.queryExecution().optimizedPlan().toString()
    assert "Contains(" not in text and text.count("Relation ") == 1 and "Aggregate [text" not in text
    assert text.count("ArrowEvalPython") == 1
