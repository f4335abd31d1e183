"""Expression language of feature query and training loop, with a reference interpreter on Python values.

Collections are dictionaries (a bag maps tuples to multiplicities), records are `Record`s.  Two dialects share these
nodes: the dynamic one may look up fields by run-time names (DynProj), the static one has none of that left.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass, fields, replace
from typing import Any


class Expr:
    def __add__(self, o):
        return Add(self, lift(o))

    def __radd__(self, o):
        return Add(lift(o), self)

    def __mul__(self, o):
        return Mul(self, lift(o))

    def __rmul__(self, o):
        return Mul(lift(o), self)

    def __neg__(self):
        return Neg(self)

    def __sub__(self, o):
        return Add(self, Neg(lift(o)))

    def __rsub__(self, o):
        return Add(lift(o), Neg(self))

    def __getitem__(self, k):
        return DynProj(self, lift(k))

    def __call__(self, k):
        return Lookup(self, lift(k))


def lift(x: Any) -> Expr:
    return x if isinstance(x, Expr) else Const(x)


@dataclass(frozen=True)
class Const(Expr):
    value: Any


@dataclass(frozen=True)
class FieldName(Expr):
    """A field's name as a value."""

    name: str


@dataclass(frozen=True)
class Var(Expr):
    name: str


@dataclass(frozen=True)
class Add(Expr):
    left: Expr
    right: Expr


@dataclass(frozen=True)
class Mul(Expr):
    left: Expr
    right: Expr


@dataclass(frozen=True)
class Neg(Expr):
    arg: Expr


@dataclass(frozen=True)
class UnOp(Expr):
    op: str
    arg: Expr


@dataclass(frozen=True)
class BinOp(Expr):
    op: str
    left: Expr
    right: Expr


@dataclass(frozen=True)
class Fold(Expr):
    """Sum, by a monoid, of body for var over the elements of a set or the keys of a dictionary."""

    var: str
    over: Expr
    body: Expr
    monoid: str = "sum"


@dataclass(frozen=True)
class Tabulate(Expr):
    var: str
    over: Expr
    body: Expr


@dataclass(frozen=True)
class SetLit(Expr):
    items: tuple


@dataclass(frozen=True)
class MapLit(Expr):
    keys: tuple
    values: tuple


@dataclass(frozen=True)
class Keys(Expr):
    arg: Expr


@dataclass(frozen=True)
class Lookup(Expr):
    table: Expr
    key: Expr


@dataclass(frozen=True)
class Rec(Expr):
    names: tuple
    values: tuple


@dataclass(frozen=True)
class Variant(Expr):
    tag: str
    arg: Expr


@dataclass(frozen=True)
class Proj(Expr):
    arg: Expr
    field: str


@dataclass(frozen=True)
class DynProj(Expr):
    arg: Expr
    field: Expr


@dataclass(frozen=True)
class Let(Expr):
    var: str
    value: Expr
    body: Expr


@dataclass(frozen=True)
class If(Expr):
    test: Expr
    then: Expr
    other: Expr


@dataclass(frozen=True)
class Iterate(Expr):
    """var starts as init and becomes step while test holds; the value is result."""

    var: str
    init: Expr
    test: Expr
    step: Expr
    result: Expr


#: For each binder: the field of the variable, and the fields in which it is bound.
BINDERS = {Fold: ("var", ("body",)), Tabulate: ("var", ("body",)), Let: ("var", ("body",)), Iterate: ("var", ("test", "step", "result"))}


def children(e: Expr) -> list[tuple[str, Expr]]:
    out = []
    for f in fields(e):
        v = getattr(e, f.name)
        if isinstance(v, Expr):
            out.append((f.name, v))
        elif isinstance(v, tuple):
            out += [(f.name, x) for x in v if isinstance(x, Expr)]
    return out


def rebuild(e: Expr, fn) -> Expr:
    """e with fn(field name, child) in place of each child."""
    new = {}
    for f in fields(e):
        v = getattr(e, f.name)
        if isinstance(v, Expr):
            new[f.name] = fn(f.name, v)
        elif isinstance(v, tuple) and any(isinstance(x, Expr) for x in v):
            new[f.name] = tuple(fn(f.name, x) if isinstance(x, Expr) else x for x in v)
    changed = {k: v for k, v in new.items() if v is not getattr(e, k)}
    return replace(e, **changed) if changed else e


def free(e: Expr) -> frozenset[str]:
    if isinstance(e, Var):
        return frozenset([e.name])
    var, inside = BINDERS.get(type(e), (None, ()))
    out: frozenset = frozenset()
    for name, c in children(e):
        f = free(c)
        out |= f - {getattr(e, var)} if name in inside else f
    return out


_fresh = itertools.count()


def fresh(base: str) -> str:
    return f"{base.split('#')[0]}#{next(_fresh)}"


def substitute(e: Expr, name: str, value: Expr) -> Expr:
    """Capture-avoiding."""
    if isinstance(e, Var):
        return value if e.name == name else e
    if name not in free(e):
        return e
    var, inside = BINDERS.get(type(e), (None, ()))
    if var:
        bound = getattr(e, var)
        if bound in free(value) and bound != name:
            new = fresh(bound)
            e = replace(rebuild(e, lambda f, c: substitute(c, bound, Var(new)) if f in inside else c), **{var: new})
            bound = new
        return rebuild(e, lambda f, c: c if f in inside and bound == name else substitute(c, name, value))
    return rebuild(e, lambda f, c: substitute(c, name, value))


def alpha_equal(a: Expr, b: Expr) -> bool:
    if type(a) is not type(b):
        return False
    var, inside = BINDERS.get(type(a), (None, ()))
    if var and getattr(a, var) != getattr(b, var):
        new = fresh("v")
        a, b = (replace(rebuild(x, lambda f, c, x=x: substitute(c, getattr(x, var), Var(new)) if f in inside else c), **{var: new}) for x in (a, b))
    for f in fields(a):
        x, y = getattr(a, f.name), getattr(b, f.name)
        if isinstance(x, Expr):
            if not isinstance(y, Expr) or not alpha_equal(x, y):
                return False
        elif isinstance(x, tuple):
            if not isinstance(y, tuple) or len(x) != len(y) or not all(alpha_equal(p, q) if isinstance(p, Expr) and isinstance(q, Expr) else p == q for p, q in zip(x, y)):
                return False
        elif x != y:
            return False
    return True


class Record(tuple):
    """Field-name pairs in a fixed order; hashable, so it can be a key."""

    def __new__(cls, pairs):
        return super().__new__(cls, tuple(sorted(dict(pairs).items())))

    def get(self, name):
        for k, v in self:
            if k == name:
                return v
        raise KeyError(name)

    def names(self):
        return [k for k, _ in self]


class Tagged(Record):
    """A variant: a record of which one field has a value."""


MONOIDS = {"sum": (lambda: 0, lambda a, b: add(a, b)), "min": (lambda: None, lambda a, b: b if a is None else a if b is None else min(a, b)), "max": (lambda: None, lambda a, b: b if a is None else a if b is None else max(a, b)), "union": (frozenset, lambda a, b: a | b), "bag": (dict, lambda a, b: add(a, b)), "any": (lambda: False, lambda a, b: a or b), "all": (lambda: True, lambda a, b: a and b)}


def add(a, b):
    if isinstance(a, dict) or isinstance(b, dict):
        a, b = a or {}, b or {}
        return {k: add(a.get(k, 0), b.get(k, 0)) for k in [*a, *(k for k in b if k not in a)]}
    if isinstance(a, Record) or isinstance(b, Record):
        if not a or not b:
            return a or b
        return Record({k: add(v, b.get(k)) for k, v in a})
    if isinstance(a, frozenset):
        return a | (b or frozenset())
    return a + b


def times(a, b):
    if isinstance(a, dict):
        return {k: times(v, b) for k, v in a.items()}
    if isinstance(b, dict):
        return {k: times(a, v) for k, v in b.items()}
    if isinstance(a, Record) and isinstance(b, Record):
        return Record({k: times(v, b.get(k)) for k, v in a})
    if isinstance(a, Record):
        return Record({k: times(v, b) for k, v in a})
    if isinstance(b, Record):
        return times(b, a)
    return a * b


def negated(a):
    return times(a, -1)


def _is_zero(v) -> bool:
    return not isinstance(v, (dict, Record, frozenset, str)) and v == 0


def part(v, name):
    """A field; the ring's zero has zero in every field."""
    return 0 if _is_zero(v) else v.get(name)


UNARY = {"not": lambda a: not a, "abs": abs, "sqrt": lambda a: a**0.5, "size": len, "int": int, "inv": lambda a: 1 / a}
BINARY = {"==": lambda a, b: a == b, "!=": lambda a, b: a != b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b, "/": lambda a, b: a / b, "and": lambda a, b: a and b, "or": lambda a, b: a or b, "in": lambda a, b: a in b, "min": min, "max": max}


def interpret(e: Expr, env: dict[str, Any] | None = None, limit: int = 100_000):
    """Value of e.  A missing key looks up as the ring's zero."""
    env = env or {}

    def run(x: Expr, env: dict):
        match x:
            case Const(v):
                return v
            case FieldName(n):
                return n
            case Var(n):
                return env[n]
            case Add(a, b):
                return add(run(a, env), run(b, env))
            case Mul(a, b):
                return times(run(a, env), run(b, env))
            case Neg(a):
                return negated(run(a, env))
            case UnOp(op, a):
                return UNARY[op](run(a, env))
            case BinOp(op, a, b):
                return BINARY[op](run(a, env), run(b, env))
            case Fold(v, over, body, monoid):
                zero, plus = MONOIDS[monoid]
                out = zero()
                for item in run(over, env):
                    out = plus(out, run(body, env | {v: item}))
                return out
            case Tabulate(v, over, body):
                return {item: run(body, env | {v: item}) for item in run(over, env)}
            case SetLit(items):
                return tuple(dict.fromkeys(run(i, env) for i in items))
            case MapLit(keys, values):
                out: dict = {}
                for k, val in zip(keys, values):
                    out = add(out, {run(k, env): run(val, env)})
                return out
            case Keys(a):
                got = run(a, env)
                return tuple(got.names() if isinstance(got, Record) else got)
            case Lookup(t, k):
                table, key = run(t, env), run(k, env)
                return part(table, key) if isinstance(table, Record) or _is_zero(table) else table.get(key, 0)
            case Rec(names, values):
                return Record(zip(names, [run(v, env) for v in values]))
            case Variant(tag, a):
                return Tagged({tag: run(a, env)})
            case Proj(a, f):
                return part(run(a, env), f)
            case DynProj(a, f):
                return part(run(a, env), run(f, env))
            case Let(v, value, body):
                return run(body, env | {v: run(value, env)})
            case If(t, a, b):
                return run(a if run(t, env) else b, env)
            case Iterate(v, init, test, step, result):
                env = env | {v: run(init, env), "round": 0}
                while run(test, env):
                    env = env | {v: run(step, env), "round": env["round"] + 1}
                    if env["round"] > limit:
                        raise RuntimeError("loop does not end")
                return run(result, env)
        raise TypeError(x)

    return run(e, env)


def show(e: Expr) -> str:
    """One line of text."""
    match e:
        case Const(v):
            return repr(v)
        case FieldName(n):
            return f"`{n}`"
        case Var(n):
            return n
        case Add(a, Neg(b)):
            return f"({show(a)} - {show(b)})"
        case Add(a, b):
            return f"({show(a)} + {show(b)})"
        case Mul(a, b):
            return f"{show(a)} * {show(b)}"
        case Neg(a):
            return f"-({show(a)})"
        case UnOp(op, a):
            return f"{op}({show(a)})"
        case BinOp(op, a, b):
            return f"({show(a)} {op} {show(b)})"
        case Fold(v, o, b, m):
            return f"{m}[{v} in {show(o)}]({show(b)})"
        case Tabulate(v, o, b):
            return f"table[{v} in {show(o)}]({show(b)})"
        case SetLit(items):
            return "[" + ", ".join(map(show, items)) + "]"
        case MapLit(k, v):
            return "{" + ", ".join(f"{show(a)}: {show(b)}" for a, b in zip(k, v)) + "}"
        case Keys(a):
            return f"keys({show(a)})"
        case Lookup(t, k):
            return f"{show(t)}({show(k)})"
        case Rec(n, v):
            return "<" + ", ".join(f"{a}={show(b)}" for a, b in zip(n, v)) + ">"
        case Variant(t, a):
            return f"{t}!{show(a)}"
        case Proj(a, f):
            return f"{show(a)}.{f}"
        case DynProj(a, f):
            return f"{show(a)}[{show(f)}]"
        case Let(v, a, b):
            return f"let {v} = {show(a)} in {show(b)}"
        case If(t, a, b):
            return f"if {show(t)} then {show(a)} else {show(b)}"
        case Iterate(v, i, t, s, r):
            return f"{v} <- {show(i)} while {show(t)} do {v} <- {show(s)} end {show(r)}"
    raise TypeError(e)
