"""Rewrite rules, one function each, and the phases that drive them.

A rule takes an expression and returns a new one, or None where it does not apply.  Rules that undo each other live in
different phases, and a fix-point is sought only inside a phase.
"""

from __future__ import annotations

from collections.abc import Callable

from .ir import BINDERS, Add, Const, DynProj, Expr, FieldName, Fold, If, Iterate, Keys, Let, Lookup, MapLit, Mul, Neg, Proj, Rec, SetLit, Tabulate, Var, alpha_equal, children, free, fresh, rebuild, substitute

Rule = Callable[[Expr], Expr | None]


# --- normal form: sums of products


def norm_distribute(e: Expr) -> Expr | None:
    match e:
        case Mul(a, Add(b, c)):
            return Add(Mul(a, b), Mul(a, c))
        case Mul(Add(b, c), a):
            return Add(Mul(b, a), Mul(c, a))


def norm_push_factor(e: Expr) -> Expr | None:
    match e:
        case Mul(a, Fold(v, over, body, "sum")):
            left = True
        case Mul(Fold(v, over, body, "sum"), a):
            left = False
        case _:
            return None
    if v in free(a):
        new = fresh(v)
        v, body = new, substitute(body, v, Var(new))
    return Fold(v, over, Mul(a, body) if left else Mul(body, a))


def norm_neg_product(e: Expr) -> Expr | None:
    match e:
        case Mul(a, Neg(b)) | Mul(Neg(a), b):
            return Neg(Mul(a, b))


def norm_neg_fold(e: Expr) -> Expr | None:
    match e:
        case Neg(Fold(v, over, body, "sum")):
            return Fold(v, over, Neg(body))


def norm_neg_sum(e: Expr) -> Expr | None:
    match e:
        case Neg(Add(a, b)):
            return Add(Neg(a), Neg(b))
        case Neg(Neg(a)):
            return a


def norm_split_fold(e: Expr) -> Expr | None:
    """A sum of sums over data is two sums."""
    match e:
        case Fold(v, Keys() as over, Add(a, b), "sum"):
            return Add(Fold(v, over, a), Fold(v, over, b))


# --- loop order


def schedule_loops(sizes: Callable[[Expr], float]) -> Rule:
    """Swap nested sums so that the smaller collection is outside.  With more features than rows it does nothing, and
    neither memoisation nor hoisting finds anything to do then."""

    def rule(e: Expr) -> Expr | None:
        match e:
            case Fold(x, a, body, "sum"):
                path, inner = [], body
                while isinstance(inner, Mul):  # the inner sum may stand behind row-wise factors
                    side = next((s for s in ("right", "left") if isinstance(getattr(inner, s), (Fold, Mul)) and _has_fold(getattr(inner, s))), None)
                    if side is None:
                        return None
                    path.append((inner, side))
                    inner = getattr(inner, side)
                if not isinstance(inner, Fold) or inner.monoid != "sum" or x in free(inner.over) or inner.var == x:
                    return None
                if not sizes(a) > sizes(inner.over):
                    return None
                y, rest = inner.var, inner.body
                for m, side in reversed(path):
                    other = getattr(m, "left" if side == "right" else "right")
                    if y in free(other):
                        return None
                    rest = Mul(other, rest) if side == "right" else Mul(rest, other)
                if y in free(a):
                    return None
                return Fold(y, inner.over, Fold(x, a, rest))
        return None

    rule.__name__ = "schedule_loops"
    return rule


def _has_fold(e: Expr) -> bool:
    return isinstance(e, Fold) or isinstance(e, Mul) and (_has_fold(e.left) or _has_fold(e.right))


# --- factoring


def factors(e: Expr) -> list[Expr]:
    return factors(e.left) + factors(e.right) if isinstance(e, Mul) else [e]


def product(items: list[Expr]) -> Expr:
    out = items[0] if items else Const(1)
    for i in items[1:]:
        out = Mul(out, i)
    return out


def factor_common(e: Expr) -> Expr | None:
    match e:
        case Add(a, b):
            left, right = factors(a), factors(b)
            if len(left) < 2 and len(right) < 2:
                return None
            for f in left:
                for g in right:
                    if alpha_equal(f, g) and not isinstance(f, Const):
                        left.remove(f)
                        right.remove(g)
                        return Mul(f, Add(product(left), product(right)))


def factor_out_of_fold(e: Expr) -> Expr | None:
    match e:
        case Fold(v, over, Neg(body), "sum"):
            return Neg(Fold(v, over, body))
        case Fold(v, over, body, "sum"):
            items = factors(body)
            out = [f for f in items if v not in free(f)]
            inside = [f for f in items if v in free(f)]
            if out and not (len(items) == 1 and isinstance(body, Const)):
                return Mul(product(out), Fold(v, over, product(inside)))


# --- memoisation and hoisting


def memoise_static(static: Callable[[Expr], bool], data: Callable[[Expr], bool], most: int = 4096) -> Rule:
    """In a sum or dictionary over a static domain, name the data-dependent sums of its body as a dictionary over it."""

    def find(e: Expr, v: str, bound: frozenset) -> Fold | None:
        if isinstance(e, Fold) and data(e.over) and v in free(e) and not (free(e) & bound):
            return e
        var, inside = BINDERS.get(type(e), (None, ()))
        for name, c in children(e):
            if got := find(c, v, bound | {getattr(e, var)} if name in inside else bound):
                return got
        return None

    def table_in(e: Expr, v: str, bound: frozenset) -> Tabulate | None:
        """A memo table made further in that still depends on v."""
        match e:
            case Let(z, Tabulate() as t, _) if v in free(t) and data_inside(t) and not (free(t) & bound):
                return t
        var, inside = BINDERS.get(type(e), (None, ()))
        for name, c in children(e):
            if got := table_in(c, v, bound | {getattr(e, var)} if name in inside else bound):
                return got
        return None

    def data_inside(e: Expr) -> bool:
        return isinstance(e, Fold) and data(e.over) or any(data_inside(c) for _, c in children(e))

    def swap(e: Expr, old: Expr, new: Expr) -> Expr:
        return new if e == old else rebuild(e, lambda _, c: swap(c, old, new))

    def rule(e: Expr) -> Expr | None:
        if not isinstance(e, (Fold, Tabulate)) or not static(e.over):
            return None
        hit = table_in(e.body, e.var, frozenset()) or find(e.body, e.var, frozenset())
        if hit is None or e.body == hit:
            return None
        z = fresh("M")
        memo = Tabulate(e.var, e.over, hit)
        body = swap(e.body, hit, Lookup(Var(z), Var(e.var)))
        kind = type(e)
        inner = Fold(e.var, e.over, body, e.monoid) if kind is Fold else Tabulate(e.var, e.over, body)
        return Let(z, memo, inner)

    rule.__name__ = "memoise_static"
    return rule


def hoist_from_fold(e: Expr) -> Expr | None:
    match e:
        case Fold(v, over, Let(y, value, body), m) if v not in free(value) and y not in free(over):
            return Let(y, value, Fold(v, over, body, m))
        case Tabulate(v, over, Let(y, value, body)) if v not in free(value) and y not in free(over):
            return Let(y, value, Tabulate(v, over, body))
        case Add(a, Let(y, value, body)) if y not in free(a):
            return Let(y, value, Add(a, body))
        case Add(Let(y, value, body), a) if y not in free(a):
            return Let(y, value, Add(body, a))
        case Mul(a, Let(y, value, body)) if y not in free(a):
            return Let(y, value, Mul(a, body))
        case Neg(Let(y, value, body)):
            return Let(y, value, Neg(body))


def hoist_from_loop(e: Expr) -> Expr | None:
    match e:
        case Iterate(x, init, test, Let(y, value, step), result) if x not in free(value) and "round" not in free(value) and y not in free(init) | free(test) | free(result):
            return Let(y, value, Iterate(x, init, test, step, result))


# --- partial evaluation


def unroll_fold(e: Expr) -> Expr | None:
    match e:
        case Fold(v, SetLit(items), body, "sum") if items:
            out = substitute(body, v, items[0])
            for i in items[1:]:
                out = Add(out, substitute(body, v, i))
            return out


def _closed(e: Expr) -> bool:
    return isinstance(e, (Const, FieldName))


def merge_same_key(e: Expr) -> Expr | None:
    match e:
        case Add(MapLit((k,), (a,)), MapLit((l,), (b,))) if k == l:
            return MapLit((k,), (Add(a, b),))


def merge_diff_key(e: Expr) -> Expr | None:
    """Only where the keys are closed and all different."""
    match e:
        case Add(MapLit(ks, a), MapLit(ls, b)) if all(map(_closed, ks + ls)) and not set(ks) & set(ls):
            return MapLit(ks + ls, a + b)


# --- schema specialisation


def spec_access(e: Expr) -> Expr | None:
    match e:
        case DynProj(a, FieldName(f)):
            return Proj(a, f)
        case DynProj(a, Const(str() as f)):
            return Proj(a, f)


def spec_dict(e: Expr) -> Expr | None:
    match e:
        case MapLit(ks, vs) if ks and all(isinstance(k, FieldName) for k in ks) and len(set(ks)) == len(ks):
            return Rec(tuple(k.name for k in ks), vs)


def spec_lookup(e: Expr) -> Expr | None:
    """A look-up in a dictionary that has become a record, by itself or through its let."""
    match e:
        case Lookup(Rec() as r, k):
            return DynProj(r, k)
        case Lookup(Proj() as r, k):
            return DynProj(r, k)
        case Let(v, Rec() as r, body):
            new = _records(body, v, r)
            return Let(v, r, new) if new != body else None
        case Iterate(v, Rec() as r, test, step, result):
            new = [_records(x, v, r) for x in (test, step, result)]
            return Iterate(v, r, *new) if new != [test, step, result] else None


def _records(e: Expr, v: str, shape: Expr) -> Expr:
    var, inside = BINDERS.get(type(e), (None, ()))
    e = rebuild(e, lambda f, c: c if var and getattr(e, var) == v and f in inside else _records(c, v, shape))
    match e:
        case Lookup(Var(n), k) if n == v:
            return DynProj(e.table, k)
        case Lookup(Proj(Var(n), f), k) if n == v and isinstance(shape, Rec) and f in shape.names and isinstance(shape.values[shape.names.index(f)], Rec):
            return DynProj(e.table, k)
    return e


def spec_tabulate(e: Expr) -> Expr | None:
    match e:
        case Tabulate(v, SetLit(items), body) if items and all(isinstance(i, FieldName) for i in items):
            return Rec(tuple(i.name for i in items), tuple(substitute(body, v, i) for i in items))


# --- fusion and generic rules


def fuse_folds(e: Expr) -> Expr | None:
    match e:
        case Let(x, Fold(v, over, a, "sum"), Let(y, Fold(w, over2, b, "sum"), body)) if alpha_equal(over, over2) and x not in free(b) and x not in free(over2) and x != y:
            t, z = fresh("t"), fresh(v)
            both = Fold(z, over, Rec((x, y), (substitute(a, v, Var(z)), substitute(b, w, Var(z)))))
            return Let(t, both, substitute(substitute(body, x, Proj(Var(t), x)), y, Proj(Var(t), y)))


def gen_inline(e: Expr) -> Expr | None:
    match e:
        case Let(x, value, body) if isinstance(value, (Const, Var, FieldName, SetLit)):
            return substitute(body, x, value)


def gen_dead(e: Expr) -> Expr | None:
    match e:
        case Let(x, _, body) if x not in free(body):
            return body


def gen_flatten(e: Expr) -> Expr | None:
    match e:
        case Let(x, Let(y, a, b), body):
            if y in free(body):
                new = fresh(y)
                b, y = substitute(b, y, Var(new)), new
            return Let(y, a, Let(x, b, body))


def gen_cse(e: Expr) -> Expr | None:
    match e:
        case Let(x, a, Let(y, b, body)) if x != y and x not in free(b) and alpha_equal(a, b):
            return Let(x, a, substitute(body, y, Var(x)))


# --- driver


def everywhere(e: Expr, rules: list[Rule], fired: list[str] | None = None, most: int = 10_000) -> Expr:
    """Fix-point of the rules over all sub-expressions, outermost first."""
    left = [most]

    def once(x: Expr) -> Expr:
        for r in rules:
            while (new := r(x)) is not None:
                if fired is not None:
                    fired.append(r.__name__)
                left[0] -= 1
                if left[0] < 0:
                    raise RuntimeError(f"{r.__name__} does not come to rest")
                x = new
        return rebuild(x, lambda _, c: once(c))

    while True:
        new = once(e)
        if new == e:
            return e
        e = new


def innermost(e: Expr, rules: list[Rule], fired: list[str] | None = None) -> Expr:
    def once(x: Expr) -> Expr:
        x = rebuild(x, lambda _, c: once(c))
        for r in rules:
            if (new := r(x)) is not None:
                if fired is not None:
                    fired.append(r.__name__)
                x = new
        return x

    while True:
        new = once(e)
        if new == e:
            return e
        e = new


def stages(program: Expr, sizes: Callable[[Expr], float], data: Callable[[Expr], bool]) -> dict[str, Expr]:
    """The program after each high-level phase and after specialisation."""

    def static(x: Expr) -> bool:
        return isinstance(x, SetLit) and len(x.items) <= 4096

    out = {"naive": program}
    e = everywhere(program, [gen_inline])
    e = out["normalised"] = everywhere(e, [norm_distribute, norm_push_factor, norm_neg_product, norm_neg_fold, norm_neg_sum, norm_split_fold])
    e = out["scheduled"] = innermost(e, [schedule_loops(sizes)])
    e = out["factored"] = innermost(e, [factor_out_of_fold])
    e = out["memoised"] = innermost(e, [memoise_static(static, data), hoist_from_fold])
    e = out["hoisted"] = everywhere(e, [hoist_from_fold, gen_flatten, hoist_from_loop])
    e = everywhere(e, [unroll_fold, merge_same_key, merge_diff_key, spec_tabulate, spec_dict])
    e = everywhere(e, [spec_lookup, spec_access])
    e = everywhere(e, [gen_dead, gen_cse, fuse_folds])
    out["specialised"] = everywhere(e, [factor_common])
    return out
