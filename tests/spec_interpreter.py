"""An executable specification over plain Python values: every judgement rule by rule, for bags of a few elements.

The engine is compared with it; nothing in the package uses it.
"""

from __future__ import annotations

import operator
from dataclasses import dataclass, field
from functools import reduce

from backtrail.functions.patterns import CLOSED_REST, SAME, SKIP, SKIP_REST, B, Bag, Rec, Skip, at_unit, join_env, normal, proj, under
from backtrail.plans.expr import Agg, Const, Each, Empty, Expr, Field, If, IsEmpty, Let, Op, Record, Single, Table, Union, Var

OPS = {"+": operator.add, "-": operator.sub, "*": operator.mul, "=": operator.eq, "<": operator.lt, "<=": operator.le, ">": operator.gt, ">=": operator.ge, "and": lambda a, b: a and b, "or": lambda a, b: a or b, "not": operator.not_}
AGGS = {"sum": sum, "count": len, "max": lambda v: max(v, default=None), "min": lambda v: min(v, default=None)}


@dataclass
class Trace:
    expr: Expr
    parts: list = field(default_factory=list)
    taken: bool | None = None
    steps: dict = field(default_factory=dict)


class Fails(Exception):
    """A replay that does not go through."""


def names(e: Expr) -> str:
    return e.name


def run(e: Expr, env: dict):
    """Value and trace."""
    match e:
        case Const(value=v):
            return v, Trace(e)
        case Op(name=n, args=args):
            found = [run(a, env) for a in args]
            return OPS[n](*[v for v, _ in found]), Trace(e, [t for _, t in found])
        case Var() | Table():
            return env[e.name], Trace(e)
        case Let(var=x, bound=b, body=c):
            v, t = run(b, env)
            w, u = run(c, env | {x: v})
            return w, Trace(e, [t, u])
        case Record(fields=fields):
            found = {k: run(x, env) for k, x in fields}
            return {k: v for k, (v, _) in found.items()}, Trace(e, [t for _, t in found.values()])
        case Field(of=of, name=n):
            v, t = run(of, env)
            return v[n], Trace(e, [t])
        case If(cond=c, then=a, other=b):
            test, t = run(c, env)
            v, u = run(a if test else b, env)
            return v, Trace(e, [t, u], test)
        case Empty():
            return B({}), Trace(e)
        case Single(item=x):
            v, t = run(x, env)
            return B({(): v}), Trace(e, [t])
        case Union(left=a, right=b):
            (v, t), (w, u) = run(a, env), run(b, env)
            return B({(1, *k): x for k, x in v.elems.items()} | {(2, *k): x for k, x in w.elems.items()}), Trace(e, [t, u])
        case Each(var=x, source=s, body=b):
            source, t = run(s, env)
            out, steps = {}, {}
            for label, item in source.elems.items():
                v, steps[label] = run(b, env | {x: item})
                out |= {(*label, *k): y for k, y in v.elems.items()}
            return B(out), Trace(e, [t], steps=steps)
        case Agg(kind=k, bag=b):
            v, t = run(b, env)
            return AGGS[k]([next(iter(x.values())) for x in v.elems.values()]), Trace(e, [t])
        case IsEmpty(bag=b):
            v, t = run(b, env)
            return not v.elems, Trace(e, [t])
    raise TypeError(e)


def replay(t: Trace, env: dict):
    match t.expr:
        case Const(value=v):
            return v
        case Op(name=n):
            return OPS[n](*[replay(p, env) for p in t.parts])
        case Var() | Table():
            return env[t.expr.name]
        case Let(var=x):
            return replay(t.parts[1], env | {x: replay(t.parts[0], env)})
        case Record(fields=fields):
            return {k: replay(p, env) for (k, _), p in zip(fields, t.parts)}
        case Field(name=n):
            return replay(t.parts[0], env)[n]
        case If():
            if replay(t.parts[0], env) != t.taken:
                raise Fails("branch flipped")
            return replay(t.parts[1], env)
        case Empty():
            return B({})
        case Single():
            return B({(): replay(t.parts[0], env)})
        case Union():
            a, b = (replay(p, env).elems for p in t.parts)
            return B({(1, *k): x for k, x in a.items()} | {(2, *k): x for k, x in b.items()})
        case Each(var=x):
            out = {}
            for label, item in replay(t.parts[0], env).elems.items():
                if label not in t.steps:
                    raise Fails("unknown label")
                out |= {(*label, *k): y for k, y in replay(t.steps[label], env | {x: item}).elems.items()}
            return B(out)
        case Agg(kind=k):
            return AGGS[k]([next(iter(x.values())) for x in replay(t.parts[0], env).elems.values()])
        case IsEmpty():
            return not replay(t.parts[0], env).elems
    raise TypeError(t.expr)


def size(t: Trace) -> int:
    return 1 + sum(map(size, t.parts)) + sum(map(size, t.steps.values()))


def cut(t: Trace, p) -> tuple[dict, int]:
    """Demands on the variables that suffice for a pattern, and the nodes of the kept trace."""
    p = normal(p)
    if isinstance(p, Skip):
        return {}, 0
    e = t.expr

    def several(pairs):
        found = [cut(part, q) for part, q in pairs]
        return reduce(join_env, [d for d, _ in found], {}), 1 + sum(n for _, n in found)

    match e:
        case Const() | Empty():
            return {}, 1
        case Op() | Agg() | IsEmpty():
            return several((part, SAME) for part in t.parts)
        case Var() | Table():
            return {e.name: p}, 1
        case Let(var=x):
            inner, n = cut(t.parts[1], p)
            outer, m = cut(t.parts[0], inner.pop(x, SKIP))
            return join_env(inner, outer), 1 + n + m
        case Record(fields=fields):
            return several((part, proj(p, k)) for part, (k, _) in zip(t.parts, fields))
        case Field(name=n):
            return several([(t.parts[0], Rec({n: p}, SKIP_REST))])
        case If():
            return several([(t.parts[0], SAME), (t.parts[1], p)])
        case Single():
            d, n = cut(t.parts[0], at_unit(p))
            return d, 1 + n
        case Union():
            return several([(t.parts[0], under(p, (1,))), (t.parts[1], under(p, (2,)))])
        case Each(var=x):
            env, total, asked = {}, 0, {}
            open_ = isinstance(p, Bag) and p.rest == SKIP_REST
            for label, step in t.steps.items():
                own = under(p, label)
                if open_ and isinstance(own, Skip):
                    continue
                d, n = cut(step, own)
                asked[label] = d.pop(x, SKIP)
                env, total = join_env(env, d), total + n
            source, m = cut(t.parts[0], Bag(asked, SKIP_REST if open_ else CLOSED_REST))
            return join_env(env, source), 1 + total + m
    raise TypeError(e)


def cells(demand, value: B) -> set[tuple[tuple, str]]:
    """Cells of a table that a demand keeps."""
    if isinstance(demand, Skip):
        return set()
    if demand == SAME:
        return {(k, c) for k, row in value.elems.items() for c in row}
    out = set()
    for k, q in demand.elems.items():
        row = value.elems[k]
        out |= {(k, c) for c in row if not isinstance(proj(q, c), Skip)} if not isinstance(q, Skip) else set()
    return out
