"""Laws of the pattern algebra on random small values, and the distributed form beside it."""

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from backtrail.functions import frames
from backtrail.functions.patterns import CLOSED_REST, SAME, SAME_REST, SKIP, SKIP_REST, B, Bag, Lit, NoJoin, Rec, at_unit, dom, equiv, harden, join, join_env, leq, matches, materialize, normal, plus, prepend, proj, restrict, under, whole
from backtrail.operators.slicing import Demand

LABELS = [(1, 1), (1, 2), (2, 1), (3,)]
RESTS = [CLOSED_REST, SKIP_REST, SAME_REST]
scalars = st.integers(0, 2)
records = st.fixed_dictionaries({"A": scalars, "B": scalars})
bags = st.dictionaries(st.sampled_from(LABELS), records).map(B)


@st.composite
def below(draw, value):
    """A pattern that lies below a value."""
    kind = draw(st.sampled_from(["skip", "same", "listed"]))
    if kind == "skip":
        return SKIP
    if kind == "same":
        return SAME
    if isinstance(value, (dict, B)):
        parts = value if isinstance(value, dict) else value.elems
        rest = draw(st.sampled_from(RESTS))
        keys = list(parts) if rest == CLOSED_REST else draw(st.lists(st.sampled_from(list(parts)), unique=True)) if parts else []
        listed = {k: draw(below(parts[k])) for k in keys}
        return normal((Rec if isinstance(value, dict) else Bag)(listed, rest))
    return Lit(value)


@st.composite
def value_and_patterns(draw):
    value = draw(bags)
    return value, draw(below(value)), draw(below(value)), draw(bags), draw(bags)


@given(value_and_patterns())
@settings(max_examples=300, deadline=None)
def test_join_is_conjunction(case):
    value, p, q, v, w = case
    assert matches(p, value) and matches(q, value)
    both = join(p, q)
    assert matches(both, value) and leq(p, both) and leq(q, both)
    assert equiv(both, value, v) == (equiv(p, value, v) and equiv(q, value, v))
    assert join(q, p) == both and join(p, p) == normal(p)


@given(value_and_patterns())
@settings(max_examples=200, deadline=None)
def test_order(case):
    value, p, q, v, _ = case
    assert leq(SKIP, p) and leq(p, harden(p)) and leq(p, whole(value)) == (join(p, whole(value)) == whole(value))
    if leq(p, q) and equiv(q, value, v):
        assert equiv(p, value, v)
    assert equiv(materialize(p, value), value, v) == equiv(p, value, v)


@given(value_and_patterns())
@settings(max_examples=200, deadline=None)
def test_union_and_restriction(case):
    value, p, _, v, _ = case
    one, two = restrict(p, [(1,)]), restrict(p, [(2,), (3,)])
    if isinstance(p, Bag):
        assert plus(one, two) == normal(p)
        assert dom(one) | dom(two) == dom(p)
    inner = under(p, (1,))
    part = lambda b: B({k[1:]: x for k, x in b.elems.items() if k[0] == 1})
    if equiv(p, value, v):
        assert equiv(inner, part(value), part(v))
    assert under(prepend((7, 7), p), (7, 7)) == normal(p) if isinstance(p, Bag) else under(p, (7,)) == p


@given(records.flatmap(lambda v: st.tuples(st.just(v), below(v), records)))
@settings(max_examples=200, deadline=None)
def test_field_projection(case):
    value, p, other = case
    for name in value:
        q = proj(p, name)
        assert matches(q, value[name])
        if equiv(p, value, other):
            assert equiv(q, value[name], other[name])


def test_all_nine_rests():
    e = {(1,): Lit(1)}
    table = {(a, b): join(Bag(e, a), Bag(e, b)).rest for a in RESTS for b in RESTS}
    assert all(table[a, b] == (CLOSED_REST if CLOSED_REST in (a, b) else SAME_REST if SAME_REST in (a, b) else SKIP_REST) for a, b in table)
    unions = {(a, b): plus(Bag({(1,): SAME}, a), Bag({(2,): SAME}, b)).rest for a in RESTS for b in RESTS}
    assert all(unions[a, b] == next(r for r in (SKIP_REST, SAME_REST, CLOSED_REST) if r in (a, b)) for a, b in unions)


def test_corner_cases():
    assert normal(Bag({}, SKIP_REST)) == SKIP and normal(Bag({}, SAME_REST)) == SAME and normal(Bag({})) == Bag({})
    with pytest.raises(NoJoin):
        join(Bag({(1,): SKIP}), Bag({(2,): SKIP}))
    with pytest.raises(NoJoin):
        join(Bag({}), Bag({(2,): SKIP}, SKIP_REST))
    with pytest.raises(NoJoin):
        join(Lit(1), Lit(2))
    with pytest.raises(ValueError):
        plus(Bag({(1,): SKIP}), Bag({(1, 2): SKIP}))
    with pytest.raises(KeyError):
        proj(Rec({"A": SKIP}), "B")
    assert at_unit(Bag({(): Lit(1)})) == Lit(1) and at_unit(SAME) == SAME
    assert join_env({"R": SKIP}, {"R": SAME, "S": SKIP}) == {"R": SAME, "S": SKIP}
    assert join(Bag({(1,): SKIP}, SKIP_REST), Bag({(2,): SAME}, SAME_REST)) == Bag({(1,): SAME, (2,): SAME}, SAME_REST)


def demand(spark, rows, rest):
    return Demand("T", spark.createDataFrame([(k[0], *v) for k, v in rows.items()], "_l0 long, m_A int, m_B int"), rest, ["A", "B"])


def pattern(rows, rest):
    return Bag({k: normal(Rec({c: SAME for c, m in zip("AB", v) if m}, SKIP_REST)) for k, v in rows.items()}, rest)


def cells(p):
    out = set()
    for k, q in p.elems.items():
        out |= {(k, c) for c in "AB" if proj(q, c) != SKIP}
    return out


@pytest.mark.parametrize("left", RESTS)
@pytest.mark.parametrize("right", RESTS)
def test_frames_join_as_the_algebra_does(spark, left, right):
    a, b = {(1,): (1, 0), (2,): (0, 0), (3,): (0, 1)}, {(2,): (1, 0), (3,): (0, 0), (4,): (0, 1)}
    found, excluded = frames.join(demand(spark, a, left), demand(spark, b, right))
    try:
        expected = join(pattern(a, left), pattern(b, right))
    except NoJoin:
        assert excluded.count() > 0
        return
    assert excluded.count() == 0 and found.rest == expected.rest
    assert {((r["_l0"],), c) for r in found.rows.collect() for c in "AB" if r[f"m_{c}"]} == cells(expected)
