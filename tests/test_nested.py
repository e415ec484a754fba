"""Nested results beside the rule interpreter on random small tables."""

import random
from functools import reduce

import pytest

from backtrail.functions.patterns import SAME as SAME_P
from backtrail.functions.patterns import SKIP_REST, B, Bag, Rec
from backtrail.operators import nested
from backtrail.operators.checks import perturbed
from backtrail.operators.slicing import Target, fill
from backtrail.plans.expr import Field as f
from backtrail.plans.expr import IsEmpty, Agg, Var, bag, each, let, lit, rec, render, table, union, when
from backtrail.sources.catalog import Catalog, Edits
from tests import spec_interpreter as spec

x, y, z = Var("x"), Var("y"), Var("z")


def tables(rng):
    draw = lambda: rng.randint(0, 3)
    rows = lambda low, width: {(low + i,): tuple(draw() for _ in range(width)) for i in range(rng.randint(2, 4))}
    return {"R": (["A", "B"], rows(1, 2)), "S": (["B", "C"], rows(11, 2)), "T": (["C", "D"], rows(21, 2))}


def queries(rng):
    k = rng.randint(0, 3)
    leaf = each("z", table("T"), when(f(z, "C").eq(f(y, "C")), bag(rec(d=f(z, "D"), a=f(x, "A")))))
    inner = lambda more: each("y", table("S"), when(f(y, "B") <= f(x, "B"), bag(rec(c=f(y, "C"), **more))))
    value = lambda test: each("z", table("T"), when(test, bag(rec(v=f(z, "D")))))
    total, none = Agg("sum", value(f(z, "C") < f(y, "C"))), IsEmpty(value(f(z, "C").eq(f(y, "C"))))
    return {
        "one level": each("x", table("R"), bag(rec(a=f(x, "A"), ys=inner({})))),
        "two levels": each("x", table("R"), when(f(x, "A") <= k, bag(rec(a=f(x, "A"), ys=inner({"zs": leaf}))))),
        "two bags": each("x", table("R"), bag(rec(a=f(x, "B"), ys=inner({}), zs=each("z", table("T"), when(f(z, "D") > f(x, "A"), bag(rec(d=f(z, "D")))))))),
        "bag of a union": each("x", table("R"), bag(rec(a=f(x, "A"), ys=union(inner({}), bag(rec(c=f(x, "B"))))))),
        "branches": each("x", table("R"), when(f(x, "A") < f(x, "B"), bag(rec(a=f(x, "A"), ys=inner({}))), bag(rec(a=lit(9), ys=each("y", table("S"), bag(rec(c=f(y, "B")))))))),
        "let": let("Q", each("y", table("S"), when(f(y, "C") > 0, bag(rec(b=f(y, "B"), c=f(y, "C"))))), each("x", table("R"), bag(rec(a=f(x, "A"), ys=each("y", Var("Q"), when(f(y, "b").eq(f(x, "B")), bag(rec(c=f(y, "c"))))))))),
        "aggregate below": each("x", table("R"), bag(rec(a=f(x, "A"), ys=each("y", table("S"), when(f(y, "B").eq(f(x, "B")), bag(rec(n=total, e=none))))))),
    }


def dotted(label):
    return ".".join(map(str, label))


def levels(value: B, path=(), above=()):
    """Path to {whole label: scalar fields}, as the shredded frames have them."""
    out = {path: {}}
    for k, row in value.elems.items():
        label = (*above, *k)
        out[path][dotted(label)] = {c: v for c, v in row.items() if not isinstance(v, B)}
        for c, v in row.items():
            if isinstance(v, B):
                for p, rows in levels(v, (*path, c), label).items():
                    out.setdefault(p, {}).update(rows)
    return out


def pattern(value: B, picked: dict, path=(), above=()):
    """Open pattern of picked fields: ``picked`` maps (path, whole label) to fields."""
    elems = {}
    for k, row in value.elems.items():
        label = (*above, *k)
        fields = {c: SAME_P for c in picked.get((path, dotted(label)), ())}
        for c, v in row.items():
            if isinstance(v, B) and (p := pattern(v, picked, (*path, c), label)) is not None:
                fields[c] = p
        if fields:
            elems[k] = Rec(fields, SKIP_REST)
    return Bag(elems, SKIP_REST) if elems else None


def environment(small):
    return {t: B({k: dict(zip(columns, v)) for k, v in rows.items()}) for t, (columns, rows) in small.items()}


def shredded(run):
    out = {}
    for path, df in run.frames().items():
        out[path] = {}
        for r in df.collect():
            row = r.asDict()
            label, parent = row.pop("lbl"), row.pop("parent")
            assert (parent is None) == (path == ()) and (parent is None or label.startswith(f"{parent}.") or label == parent)
            row.pop("there", None)
            out[path][label] = row
    return out


@pytest.mark.parametrize("name", list(queries(random.Random(0))))
def test_nested_against_rules(spark, name):
    rng = random.Random(name)
    small = tables(rng)
    e, env, cat = queries(rng)[name], environment(small), Catalog.of_rows(spark, **small)
    value, whole = spec.run(e, env)
    run = nested.trace_nested(e, cat)
    found = shredded(run)
    expected = levels(value)
    assert {p: rows for p, rows in found.items() if rows} == {p: rows for p, rows in expected.items() if rows}
    places = [(p, k) for p, rows in expected.items() for k, row in rows.items() if row]
    if not places:
        return
    picked = {place: rng.sample(list(expected[place[0]][place[1]]), 1) for place in rng.sample(places, min(3, len(places)))}
    by_path = {}
    for (p, k), fields in picked.items():
        by_path.setdefault(p, {})[k] = fields
    target = nested.NestedTarget(run, {p: Target.cells(run.levels[p], asked) for p, asked in by_path.items()})
    demands, _ = spec.cut(whole, pattern(value, picked))
    rules = {(t, k, c) for t, d in demands.items() for k, c in spec.cells(d, env[t])}
    inputs = nested.slice_nested_inputs(target)
    engine = {(t, tuple(map(int, r["lbl"].split("."))), c) for t, d in inputs.items() for r in d.labelled().collect() for c in d.columns if r[f"m_{c}"]}
    assert engine == rules
    # Holes filled and everything outside the slice changed, the picked fields come out as before.
    partial = nested.slice_nested_query(target)
    assert "□" in render(partial) or len(places) <= 3
    again = shredded(nested.trace_nested(fill(partial, lambda: lit(0)), perturbed(cat, inputs)))
    for (p, k), fields in picked.items():
        assert {c: again[p][k][c] for c in fields} == {c: expected[p][k][c] for c in fields}


@pytest.mark.parametrize("name", ["one level", "two levels", "branches", "aggregate below"])
def test_nested_replay_against_rules(spark, name):
    rng = random.Random(name + "?")
    small = tables(rng)
    e, env, cat = queries(rng)[name], environment(small), Catalog.of_rows(spark, **small)
    _, whole = spec.run(e, env)
    run = nested.trace_nested(e, cat)
    for _ in range(2):
        t = rng.choice(list(small))
        label, column, v = rng.choice(list(small[t][1])), rng.choice(small[t][0]), rng.randint(0, 3)
        new = dict(env[t].elems)
        new[label] = new[label] | {column: v}
        try:
            spec.replay(whole, env | {t: B(new)})
            expected = True
        except spec.Fails:
            expected = False
        assert (nested.replay_nested(run, cat.apply(Edits(t).update(label, column, v))).limit(1).count() == 0) is expected


def test_nested_value_is_assembled(spark):
    rng = random.Random(8)
    small = tables(rng)
    e = queries(rng)["two levels"]
    value, _ = spec.run(e, environment(small))

    def plain(bag_, above=()):
        return {dotted((*above, *k)): {c: plain(v, (*above, *k)) if isinstance(v, B) else v for c, v in row.items()} for k, row in bag_.elems.items()}

    def read(rows):
        return {r["lbl"]: {c: read(v) if isinstance(v, list) else v for c, v in r.asDict().items() if c != "lbl"} for r in rows}

    assert read(nested.trace_nested(e, Catalog.of_rows(spark, **small)).value().collect()) == plain(value)


def test_conversations_by_turn(spark):
    """Shredding finds every bag once, and nothing else."""
    from backtrail import workloads as w

    assert list(nested.shred(w.talks())) == [(), ("turns",)] and list(nested.shred(w.selection())) == [()]
    assert reduce(lambda a, b: a and b, (not nested.is_bag(v) for h in nested._heads(nested.shred(w.nested_customers())[()]) for _, v in h.item.fields))
