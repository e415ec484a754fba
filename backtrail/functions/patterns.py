"""The algebra of patterns, on the driver: values with parts left open.

``Skip`` relates any two values, ``Same`` equal ones, ``Lit`` pins a constant.  Records and bags list some parts and say what
holds for the rest: ``CLOSED`` (nothing else exists), ``SKIP`` or ``SAME``.  Labels are tuples of naturals; values are constants,
dicts of fields, or :class:`B` for bags.
"""

from __future__ import annotations

from dataclasses import dataclass

SKIP_REST, SAME_REST, CLOSED_REST = "skip", "same", "closed"


class _Plain:
    def __repr__(self):
        return type(self).__name__


class Skip(_Plain):
    def __eq__(self, other):
        return isinstance(other, Skip)

    def __hash__(self):
        return 1


class Same(_Plain):
    def __eq__(self, other):
        return isinstance(other, Same)

    def __hash__(self):
        return 2


@dataclass(frozen=True)
class Lit:
    value: object


@dataclass(eq=True)
class Rec:
    fields: dict
    rest: str = CLOSED_REST


@dataclass(eq=True)
class Bag:
    elems: dict
    rest: str = CLOSED_REST


@dataclass(eq=True)
class B:
    """A bag value: label to element."""

    elems: dict


SKIP, SAME = Skip(), Same()


class NoJoin(ValueError):
    """Two patterns without a common refinement."""


def normal(p):
    """An open pattern that lists nothing is whole; parts likewise."""
    if isinstance(p, (Rec, Bag)):
        listed = {k: normal(v) for k, v in (p.fields if isinstance(p, Rec) else p.elems).items()}
        if not listed and p.rest != CLOSED_REST:
            return SKIP if p.rest == SKIP_REST else SAME
        return type(p)(listed, p.rest)
    return p


def _view(p, like):
    """``(listed, rest)`` of a composite pattern, or of a whole one seen as it."""
    if isinstance(p, Skip):
        return {}, SKIP_REST
    if isinstance(p, Same):
        return {}, SAME_REST
    if type(p) is not type(like):
        raise NoJoin(f"{p} and {like} differ in kind")
    return (p.fields if isinstance(p, Rec) else p.elems), p.rest


def harden(p):
    """Every skip made same."""
    match p:
        case Skip():
            return SAME
        case Rec(fields=f, rest=r):
            return normal(Rec({k: harden(v) for k, v in f.items()}, SAME_REST if r == SKIP_REST else r))
        case Bag(elems=e, rest=r):
            return normal(Bag({k: harden(v) for k, v in e.items()}, SAME_REST if r == SKIP_REST else r))
    return p


#: Rest of a join, whichever side is which.
_JOIN_REST = {frozenset([SKIP_REST]): SKIP_REST, frozenset([SAME_REST]): SAME_REST, frozenset([SKIP_REST, SAME_REST]): SAME_REST}


def join(p, q):
    """The least pattern that demands what either does."""
    if isinstance(p, Skip):
        return q
    if isinstance(q, Skip):
        return p
    composite = next((x for x in (p, q) if isinstance(x, (Rec, Bag))), None)
    if composite is None:
        if isinstance(p, Same) or isinstance(q, Same):
            return q if isinstance(p, Same) else p
        if p != q:
            raise NoJoin(f"{p} and {q} pin unlike constants")
        return p
    a, r = _view(p, composite)
    b, t = _view(q, composite)

    def alone(x, other_rest, label):
        if other_rest == CLOSED_REST:
            raise NoJoin(f"{label} is excluded by a closed pattern")
        return harden(x) if other_rest == SAME_REST else x

    listed = {k: join(a[k], b[k]) if k in a and k in b else alone(a[k], t, k) if k in a else alone(b[k], r, k) for k in [*a, *(x for x in b if x not in a)]}
    rest = CLOSED_REST if CLOSED_REST in (r, t) else _JOIN_REST[frozenset([r, t])]
    return normal(type(composite)(listed, rest))


def plus(p, q):
    """Disjoint union of bag patterns: elements side by side; a skipped rest wins over a same one, that over a closed one."""
    like = next((x for x in (p, q) if isinstance(x, Bag)), Bag({}))
    a, r = _view(p, like)
    b, t = _view(q, like)
    for x in a:
        for y in b:
            if x[: len(y)] == y or y[: len(x)] == x:
                raise ValueError(f"labels {x} and {y} are not prefix-disjoint")
    rest = next(x for x in (SKIP_REST, SAME_REST, CLOSED_REST) if x in (r, t))
    return normal(Bag(a | b, rest))


def leq(p, q) -> bool:
    """Whether ``q`` demands all that ``p`` does."""
    try:
        return join(p, q) == normal(q)
    except NoJoin:
        return False


def matches(p, value) -> bool:
    """Whether a pattern lies below a value."""
    match p:
        case Skip() | Same():
            return True
        case Lit(value=v):
            return v == value
        case Rec(fields=f, rest=r):
            return isinstance(value, dict) and all(k in value and matches(x, value[k]) for k, x in f.items()) and (r != CLOSED_REST or set(f) == set(value))
        case Bag(elems=e, rest=r):
            return isinstance(value, B) and all(k in value.elems and matches(x, value.elems[k]) for k, x in e.items()) and (r != CLOSED_REST or set(e) == set(value.elems))
    raise TypeError(p)


def equiv(p, v, w) -> bool:
    """Whether two values agree as far as a pattern demands."""
    match p:
        case Skip():
            return True
        case Same():
            return v == w
        case Lit(value=c):
            return v == c == w
        case Rec(fields=f, rest=r):
            inside = isinstance(v, dict) and isinstance(w, dict)
            return inside and all(k in v and k in w and equiv(x, v[k], w[k]) for k, x in f.items()) and _rest(f, r, v, w)
        case Bag(elems=e, rest=r):
            inside = isinstance(v, B) and isinstance(w, B)
            return inside and all(k in v.elems and k in w.elems and equiv(x, v.elems[k], w.elems[k]) for k, x in e.items()) and _rest(e, r, v.elems, w.elems)
    raise TypeError(p)


def _rest(listed, rest, v, w) -> bool:
    a, b = ({k: x for k, x in side.items() if k not in listed} for side in (v, w))
    return rest == SKIP_REST or (not a and not b if rest == CLOSED_REST else a == b)


def at_unit(p):
    """The element of a singleton."""
    if isinstance(p, (Skip, Same)):
        return p
    if () in p.elems:
        return p.elems[()]
    return {SKIP_REST: SKIP, SAME_REST: SAME}[p.rest]


def under(p, label: tuple):
    """Elements below a label, which is taken off."""
    if isinstance(p, (Skip, Same)):
        return p
    return normal(Bag({k[len(label) :]: v for k, v in p.elems.items() if k[: len(label)] == label}, p.rest))


def restrict(p, code):
    """Elements whose label extends one of a prefix code."""
    if isinstance(p, (Skip, Same)):
        return p
    return normal(Bag({k: v for k, v in p.elems.items() if any(k[: len(c)] == c for c in code)}, p.rest))


def prepend(label: tuple, p):
    if isinstance(p, (Skip, Same)):
        return p
    return Bag({(*label, *k): v for k, v in p.elems.items()}, p.rest)


def proj(p, name: str):
    """A field's pattern."""
    if isinstance(p, (Skip, Same)):
        return p
    if name in p.fields:
        return p.fields[name]
    if p.rest == CLOSED_REST:
        raise KeyError(name)
    return SKIP if p.rest == SKIP_REST else SAME


def dom(p) -> set:
    return set(p.elems) if isinstance(p, Bag) else set()


def join_env(a: dict, b: dict) -> dict:
    return {k: join(a.get(k, SKIP), b.get(k, SKIP)) for k in [*a, *(x for x in b if x not in a)]}


def materialize(p, value):
    """The pattern with same parts spelled out as the value's own."""
    match p:
        case Skip():
            return SKIP
        case Rec(fields=f, rest=r):
            listed = {k: materialize(x, value[k]) for k, x in f.items()}
            return Rec(listed | ({k: whole(v) for k, v in value.items() if k not in f} if r == SAME_REST else {}), CLOSED_REST if r == SAME_REST else r)
        case Bag(elems=e, rest=r):
            listed = {k: materialize(x, value.elems[k]) for k, x in e.items()}
            return Bag(listed | ({k: whole(v) for k, v in value.elems.items() if k not in e} if r == SAME_REST else {}), CLOSED_REST if r == SAME_REST else r)
    return whole(value)


def whole(value):
    """The pattern that pins all of a value."""
    if isinstance(value, dict):
        return Rec({k: whole(v) for k, v in value.items()})
    if isinstance(value, B):
        return Bag({k: whole(v) for k, v in value.elems.items()})
    return Lit(value)
