"""The small examples with answers derived by hand."""

import pytest

from backtrail.functions.patterns import B
from backtrail.operators.replay import replay, replay_slice
from backtrail.operators.runs import trace, trace_nodes
from backtrail.operators.slicing import Target, diff_inputs, diff_query, leq_expr, slice_inputs, slice_nodes, slice_query, slice_trace
from backtrail.plans.expr import Each, Field, Var, bag, each, lit, op, query, rec, render, table, typecheck, union, when
from backtrail.sources.catalog import Catalog, Edits
from tests import spec_interpreter as spec

R = (["A", "B", "C"], {(11,): (1, 2, 7), (12,): (2, 3, 8), (13,): (4, 3, 9)})
S = (["B", "C"], {(21,): (2, 4), (22,): (3, 4), (23,): (4, 5)})
x, y = Var("x"), Var("y")
f = Field


@pytest.fixture(scope="module")
def cat(spark):
    return Catalog.of_rows(spark, R=R, S=S)


def plain(name):
    columns, rows = {"R": R, "S": S}[name]
    return B({k: dict(zip(columns, v)) for k, v in rows.items()})


ENV = {"R": plain("R"), "S": plain("S")}

SWAP = union(each("x", table("R"), when(f(x, "A") < f(x, "B"), bag(x))), each("x", table("R"), when(op("<=", f(x, "B"), f(x, "A")), bag(rec(A=f(x, "B"), B=f(x, "A"), C=f(x, "C"))))))
SELECT = each("x", table("R"), when(f(x, "B").eq(3), bag(rec(A=f(x, "A"), B=f(x, "C")))))
CONST = union(each("x", table("R"), bag(rec(B=f(x, "B")))), bag(rec(B=lit(3))))
JOIN = query({"x": table("R"), "y": table("S")}, rec(A=f(x, "A"), B=f(y, "C")), f(x, "B").eq(f(y, "B")))


def rows(run):
    return {r["lbl"]: tuple(r)[1:] for r in run.value().collect()}


def kept(run, target):
    return {(t, r["lbl"], c) for t, d in slice_inputs(run, target).items() for r in d.labelled().collect() for c in d.columns if r[f"m_{c}"]}


@pytest.mark.parametrize(
    "expr, cells, full, part, found",
    [
        (SWAP, {"1.12": ["B"]}, 56, 11, {("R", "12", "A"), ("R", "12", "B")}),
        (SELECT, {"12": ["B"]}, 30, 11, {("R", "12", "B"), ("R", "12", "C")}),
        (CONST, {"1.12": ["B"]}, 18, 7, {("R", "12", "B")}),
        (CONST, {"2": ["B"]}, 18, 4, set()),
        (JOIN, {"11.21": ["A"], "12.22": ["B"]}, 86, 26, {("R", "11", "A"), ("R", "11", "B"), ("R", "12", "B"), ("S", "21", "B"), ("S", "22", "B"), ("S", "22", "C")}),
    ],
)
def test_open_slices(cat, expr, cells, full, part, found):
    run = trace(expr, cat)
    target = Target.cells(run, cells)
    assert spec.size(spec.run(expr, ENV)[1]) == trace_nodes(run) == full
    assert slice_nodes(slice_trace(run, target)) == part
    assert kept(run, target) == found


def test_given_labels_need_no_data(cat, spark):
    """Slices of labels taken on trust equal those looked up in the result."""
    for expr, cells in ((SWAP, {"1.12": ["B"], "2.13": ["A"]}), (SELECT, {"12": ["B"], "13": []}), (CONST, {"1.12": ["B"], "2": ["B"]}), (JOIN, {"11.21": ["A"], "12.22": ["B"]})):
        run = trace(expr, cat)
        a, b = Target.at(run, cells), Target.cells(run, cells)
        assert kept(run, a) == kept(run, b)
        assert slice_nodes(slice_trace(run, a)) == slice_nodes(slice_trace(run, b))
        assert render(slice_query(run, a)) == render(slice_query(run, b))


def test_results(cat):
    assert rows(trace(SWAP, cat)) == {"1.11": (1, 2, 7), "1.12": (2, 3, 8), "2.13": (3, 4, 9)}
    assert rows(trace(SELECT, cat)) == {"12": (2, 8), "13": (4, 9)}
    assert rows(trace(CONST, cat)) == {"1.11": (2,), "1.12": (3,), "1.13": (3,), "2": (3,)}
    assert rows(trace(JOIN, cat)) == {"11.21": (1, 4), "12.22": (2, 4), "13.22": (4, 4)}


def test_closed_slice_keeps_every_condition(cat):
    run = trace(SELECT, cat)
    target = Target.cells(run, {"12": ["B"]}).closed()
    assert kept(run, target) == {("R", "11", "B"), ("R", "12", "B"), ("R", "12", "C"), ("R", "13", "B")}
    assert slice_nodes(slice_trace(run, target)) == 23
    assert slice_inputs(run, target)["R"].rest == "closed"


def test_query_slices(cat):
    run = trace(SELECT, cat)
    partial = slice_query(run, Target.cells(run, {"12": ["B"]}))
    assert render(partial) == "∪{if (x.B = 3) then {<A: □, B: x.C>} else □ | x ∈ R}"
    assert leq_expr(partial, SELECT) and not leq_expr(SELECT, partial)
    run = trace(CONST, cat)
    assert render(slice_query(run, Target.cells(run, {"2": ["B"]}))) == "(□ ∪ {<B: 3>})"


def test_difference_is_the_projection(cat):
    run = trace(SELECT, cat)
    inner, outer = Target.cells(run, {"12": []}), Target.cells(run, {"12": ["B"]})
    for one_pass in (True, False):
        found = diff_inputs(inner, outer, one_pass)["R"].collect()
        assert {(r["lbl"], r["column"], r["level"]) for r in found} == {("12", "B", 2), ("12", "C", 1)}
    assert [r["kept"] for r in diff_query(inner, outer).orderBy("site").collect()].count(1) == 1
    assert slice_nodes(slice_trace(run, inner)) == 8 and slice_nodes(slice_trace(run, outer)) == 11


@pytest.mark.parametrize(
    "edit, full, sliced",
    [
        (lambda e: e.update((11,), "B", 5), True, True),
        (lambda e: e.update((11,), "A", 9).update((12,), "C", 1), True, True),
        (lambda e: e.update((11,), "B", 3), False, True),
        (lambda e: e.update((12,), "B", 4), False, False),
        (lambda e: e.delete((11,)), True, True),
        (lambda e: e.insert((14,), A=1, B=3, C=1), False, True),
        (lambda e: e.drop_field("A"), False, True),
    ],
)
def test_replay_verdicts(cat, edit, full, sliced):
    run = trace(SELECT, cat)
    part = slice_trace(run, Target.cells(run, {"12": ["B"]}))
    changed = cat.apply(edit(Edits("R")))
    assert replay(run, changed).ok is full
    assert replay_slice(part, changed).ok is sliced


def test_added_field_is_no_obstacle_to_a_slice(cat):
    run = trace(SELECT, cat)
    part = slice_trace(run, Target.cells(run, {"12": ["B"]}))
    assert replay_slice(part, cat.apply(Edits("R").add_field("D", 1))).ok


def test_types(cat):
    kinds = cat.types()
    assert typecheck(JOIN, kinds) == ("bag", {"A": "number", "B": "number"})
    for wrong in (each("x", table("R"), bag(rec(A=f(x, "Z")))), when(lit(3), bag(rec(A=1))), f(table("R"), "A"), Each("x", lit(1), bag(x)), union(bag(rec(A=1)), bag(rec(B=1)))):
        with pytest.raises(TypeError):
            typecheck(wrong, kinds)


def test_texts_and_types_of_runs(cat, tmp_path):
    from backtrail.operators.measure import probe_precision, stored_bytes
    from backtrail.operators.runs import render_trace, typecheck_trace
    from backtrail.operators.slicing import render_diff

    run = trace(SELECT, cat, "lazy", "full")
    assert "[11] (x.B = 3) is false: else" in render_trace(run) and "[12] (x.B = 3) is true: then" in render_trace(run)
    assert typecheck_trace(run) == [] and typecheck_trace(trace(CONST, cat)) == []
    assert stored_bytes(run, str(tmp_path / "t")) > 0 and stored_bytes(trace(SELECT, cat), str(tmp_path / "u")) == 0
    inner, outer = Target.cells(run, {"12": []}), Target.cells(run, {"12": ["B"]})
    assert render_diff(inner, outer) == "∪{if (x.B = 3) then {<A: □, B: [x.C]>} else □ | x ∈ R}"
    found = probe_precision(run, outer)
    assert 0 < found["changing"] <= found["probed"] == found["kept"] == 2
