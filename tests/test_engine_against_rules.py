"""The engine beside the rule interpreter on random small tables and queries."""

import random

import pytest
from pyspark.sql import functions as F

from backtrail.functions.patterns import CLOSED_REST, SKIP_REST, B, Bag, Rec, SAME as SAME_P, SKIP as SKIP_P
from backtrail.operators.checks import query_slice_violations, slice_violations
from backtrail.operators.replay import can_replay, replay
from backtrail.operators.runs import trace, trace_nodes
from backtrail.operators.slicing import Target, slice_inputs, slice_nodes, slice_trace
from backtrail.plans.blocks import aggregates
from backtrail.plans.expr import Field as f
from backtrail.plans.expr import Agg, IsEmpty, Var, bag, each, intersect, let, lit, minus, op, query, rec, select, table, union, when
from backtrail.sources.catalog import Catalog, Edits
from tests import spec_interpreter as spec

x, y, z = Var("x"), Var("y"), Var("z")


def tables(rng):
    draw = lambda: rng.randint(0, 3)
    return {"R": (["A", "B", "C"], {(i,): (draw(), draw(), draw()) for i in range(1, rng.randint(3, 6))}), "S": (["B", "C"], {(i,): (draw(), draw()) for i in range(11, rng.randint(13, 16))})}


def queries(rng):
    k = rng.randint(0, 3)
    return {
        "select": select(table("R"), lambda r: f(r, "B") <= k, lambda r: rec(A=f(r, "A") + f(r, "C"), B=f(r, "C"))),
        "whole": each("x", table("R"), when(f(x, "A") < f(x, "B"), bag(x))),
        "join": query({"x": table("R"), "y": table("S")}, rec(A=f(x, "A"), B=f(y, "C")), f(x, "B").eq(f(y, "B"))),
        "nested guards": each("x", table("R"), when(f(x, "A") > k - 1, each("y", table("S"), when(f(x, "B").eq(f(y, "B")), bag(rec(A=f(x, "C"), B=f(y, "C"))))))),
        "self join": query({"x": table("R"), "y": table("R")}, rec(A=f(x, "A"), B=f(y, "C")), (f(x, "A") < f(y, "A")) & f(x, "B").eq(f(y, "C"))),
        "product": each("x", table("R"), each("y", table("S"), bag(rec(A=f(x, "A"), B=f(y, "B"))))),
        "union": union(each("x", table("R"), when(f(x, "A").eq(k), bag(rec(A=f(x, "A"), B=f(x, "B"))))), each("y", table("S"), bag(rec(A=f(y, "B"), B=lit(k))))),
        "let": let("T", each("x", table("R"), when(f(x, "C") > 0, bag(rec(k=f(x, "B"), v=f(x, "A"))))), query({"z": Var("T"), "y": table("S")}, rec(A=f(z, "v"), B=f(y, "C")), f(z, "k").eq(f(y, "B")))),
        "minus": minus(table("R"), table("S"), lambda a, b: f(a, "B").eq(f(b, "B")), lambda a: rec(A=f(a, "A"), B=f(a, "C"))),
        "test in a conjunction": each("x", table("R"), when((f(x, "A") >= k) & IsEmpty(each("y", table("S"), when(f(y, "C") < f(x, "B"), bag(rec(o=lit(1)))))), bag(rec(A=f(x, "A"), B=f(x, "C"))))),
        "test in a head": each("x", table("R"), bag(rec(A=f(x, "A"), B=IsEmpty(union(each("y", table("S"), when(f(y, "B").eq(f(x, "B")), bag(rec(o=lit(1))))), each("y", table("R"), when(f(y, "A") > f(x, "A"), bag(rec(o=lit(1)))))))))),
        "sum by order": each("x", table("R"), bag(rec(A=f(x, "A"), B=Agg("sum", each("y", table("S"), when(f(y, "B") < f(x, "B"), bag(rec(v=f(y, "C"))))))))),
        "count in a condition": each("x", table("R"), when(Agg("count", each("y", table("S"), when(f(y, "B").eq(f(x, "B")), bag(rec(v=f(y, "C")))))) > 0, bag(rec(A=f(x, "A"), B=f(x, "C"))))),
        "not both empty": each("x", table("R"), when(op("not", IsEmpty(union(each("y", table("S"), when(f(y, "B").eq(f(x, "B")), bag(rec(o=lit(1))))), each("y", table("S"), when(f(y, "C").eq(f(x, "A")), bag(rec(o=lit(1)))))))), bag(rec(A=f(x, "A"), B=f(x, "C"))))),
        "intersect": intersect(table("R"), table("S"), lambda a, b: f(a, "B").eq(f(b, "B")), lambda a: rec(A=f(a, "A"), B=f(a, "C"))),
    }


def dotted(label):
    return ".".join(map(str, label))


def engine_cells(run, target):
    return {(t, tuple(map(int, r["lbl"].split("."))), c) for t, d in slice_inputs(run, target).items() for r in d.labelled().collect() for c in d.columns if r[f"m_{c}"]}


def rule_cells(demands, env):
    return {(t, k, c) for t, d in demands.items() for k, c in spec.cells(d, env[t])}


@pytest.mark.parametrize("name", list(queries(random.Random(0))))
def test_against_rules(spark, name):
    rng = random.Random(name)
    small = tables(rng)
    e = queries(rng)[name]
    env = {t: B({k: dict(zip(columns, v)) for k, v in rows.items()}) for t, (columns, rows) in small.items()}
    cat = Catalog.of_rows(spark, **small)
    value, whole = spec.run(e, env)
    run = trace(e, cat)
    assert {r["lbl"]: tuple(r)[1:] for r in run.value().collect()} == {dotted(k): tuple(v.values()) for k, v in value.elems.items()}
    counts_nodes = name not in ("minus", "intersect", "let", "test in a conjunction", "test in a head", "sum by order", "count in a condition", "not both empty")
    if counts_nodes:
        assert trace_nodes(run) == spec.size(whole)
    labels = sorted(value.elems)
    if not labels:
        return
    picked = {k: rng.sample(list(value.elems[k]), rng.randint(1, len(value.elems[k]))) for k in rng.sample(labels, min(2, len(labels)))}
    target = Target.cells(run, {dotted(k): v for k, v in picked.items()})
    elems = {k: Rec({c: SAME_P for c in v}, SKIP_REST) for k, v in picked.items()}
    patterns = {"open": (target, Bag(elems, SKIP_REST)), "closed": (target.closed(), Bag({k: elems.get(k, SKIP_P) for k in labels}, CLOSED_REST)), "same": (target.same(), SAME_P)}
    for kind, (t, p) in patterns.items():
        demands, nodes = spec.cut(whole, p)
        assert engine_cells(run, t) == rule_cells(demands, env), kind
        if counts_nodes:
            assert slice_nodes(slice_trace(run, t)) == nodes, kind
    if not any(aggregates(g.cond) for b in run.blocks for g in b.guards) and not any(aggregates(b.head) for b in run.blocks):
        for mode in ("eager", "lazy") if name in ("join", "union") else ("eager",):  # the same slices from the recorded trace, whatever has become of the tables
            again = trace(e, Catalog.of_rows(spark, **small), mode, "full")
            if mode == "eager":
                for t, df in again.cat.tables.items():
                    again.cat.tables[t] = df.select(*again.cat.labels(t), *[F.lit(-1).cast("long").alias(c) for c in again.cat.columns(t)])
            stored = Target.cells(again, {dotted(k): v for k, v in picked.items()})
            for kind, t in {"open": stored, "closed": stored.closed(), "same": stored.same()}.items():
                demands, nodes = spec.cut(whole, patterns[kind][1])
                assert engine_cells(again, t) == rule_cells(demands, env), (mode, kind)
                if counts_nodes:
                    assert slice_nodes(slice_trace(again, t)) == nodes, (mode, kind)
    assert slice_violations(run, target).count() == 0
    assert slice_violations(run, target.closed()).count() == 0
    if name != "whole":
        assert query_slice_violations(run, target, chooser=lambda: lit(0)).count() == 0


@pytest.mark.parametrize("name", ["select", "join", "nested guards", "self join", "union", "minus", "let", "test in a conjunction", "test in a head", "count in a condition", "sum by order"])
def test_replay_against_rules(spark, name):
    rng = random.Random(name + "!")
    small = tables(rng)
    e = queries(rng)[name]
    run = trace(e, Catalog.of_rows(spark, **small))
    env = {t: B({k: dict(zip(columns, v)) for k, v in rows.items()}) for t, (columns, rows) in small.items()}
    _, whole = spec.run(e, env)
    verdicts = set()
    for i in range(6 if name in ("self join", "minus") else 3):
        t = rng.choice(["R", "S"])
        columns, rows = small[t]
        edits, new, label = Edits(t), dict(env[t].elems), rng.choice(list(rows))
        match i % 3:
            case 0:
                c, v = rng.choice(columns), rng.randint(0, 3)
                edits.update(label, c, v)
                new[label] = new[label] | {c: v}
            case 1:
                edits.delete(label)
                del new[label]
            case _:
                values = {c: rng.randint(0, 3) for c in columns}
                edits.insert((99,), **values)
                new[(99,)] = values
        try:
            spec.replay(whole, env | {t: B(new)})
            expected = True
        except spec.Fails:
            expected = False
        verdicts.add(expected)
        found = replay(run, run.cat.apply(edits))
        assert found.ok is expected, (i, t)
        assert sorted(map(tuple, can_replay(run, edits).collect())) == sorted(map(tuple, found.failures.collect())), (i, t)
    assert verdicts


def test_labels_must_be_in_the_result(spark):
    """Given labels are looked up: an absent one, or an unknown field, is no target."""
    cat = Catalog.of_rows(spark, R=(["A", "B"], {(1,): (1, 2), (2,): (3, 2)}), S=(["B", "C"], {(11,): (9, 4)}))
    run = trace(query({"x": table("R"), "y": table("S")}, rec(A=f(x, "A"), C=f(y, "C")), f(x, "B").eq(f(y, "B"))), cat)
    with pytest.raises(ValueError):
        Target.at(run, {"1.11": ["A"]})
    pick = trace(select(table("R"), lambda r: f(r, "A") > 1, lambda r: rec(A=f(r, "A"))), cat)
    assert {t: [tuple(r) for r in d.rows.collect()] for t, d in slice_inputs(pick, Target.at(pick, {"2": ["A"]})).items()} == {"R": [(2, 1, 0)]}
    for cells in ({"1": ["A"]}, {"2": ["B"]}, {"7": ["A"]}, {"2.1": ["A"]}):
        with pytest.raises(ValueError):
            Target.at(pick, cells)


def test_determinism_of_primitives():
    from backtrail.plans.expr import primitive

    with pytest.raises(ValueError):
        primitive("dice", lambda a: a, "number", deterministic=False)
    assert op("+", 1, 2).name == "+"
