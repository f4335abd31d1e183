"""Reads a restricted Python function as a program of the language.

Statements: assignments, one `while` loop over one variable, a final return.  Expressions: arithmetic, comparisons, x[f],
d(k), {f: e for f in F}, sum(e for x in Q), {k: v}, [..], conditional expressions, a.f, and names of fields in quotes.
"""

from __future__ import annotations

import ast
import inspect
import textwrap

from .ir import Add, BinOp, Const, DynProj, Expr, FieldName, Fold, If, Iterate, Keys, Let, Lookup, MapLit, Mul, Neg, Proj, SetLit, Tabulate, UnOp, Var

_COMPARE = {ast.Eq: "==", ast.NotEq: "!=", ast.Lt: "<", ast.LtE: "<=", ast.Gt: ">", ast.GtE: ">=", ast.In: "in"}
_MONOID = {"sum": "sum", "min": "min", "max": "max", "any": "any", "all": "all"}


def program(fn) -> Expr:
    """The body of fn as an expression whose free variables are fn's parameters."""
    body = ast.parse(textwrap.dedent(inspect.getsource(fn))).body[0].body
    return _block(body)


def program_of(source: str) -> Expr:
    """A program given as text: the statements of a function's body."""
    text = "def f():\n" + textwrap.indent(textwrap.dedent(source), "    ")
    return _block(ast.parse(text).body[0].body)


def parse(source: str) -> Expr:
    return _expr(ast.parse(source, mode="eval").body)


def _block(body: list[ast.stmt]) -> Expr:
    head, rest = body[0], body[1:]
    match head:
        case ast.Expr(ast.Constant(str())):
            return _block(rest)
        case ast.Return(value):
            return _expr(value)
        case ast.Assign([ast.Name(x)], value) if rest and isinstance(rest[0], ast.While):
            loop = rest[0]
            lets = loop.body[:-1]
            match loop.body[-1]:
                case ast.Assign([ast.Name(y)], step) if y == x:
                    inner = _expr(step)
                case _:
                    raise SyntaxError("the loop must end by giving its variable a new value")
            for s in reversed(lets):
                inner = Let(s.targets[0].id, _expr(s.value), inner)
            return Iterate(x, _expr(value), _expr(loop.test), inner, _block(rest[1:]))
        case ast.Assign([ast.Name(x)], value):
            return Let(x, _expr(value), _block(rest))
    raise SyntaxError(f"not in the language: {ast.unparse(head)}")


def _expr(e: ast.expr) -> Expr:
    match e:
        case ast.Constant(str() as v):
            return FieldName(v)
        case ast.Constant(v):
            return Const(v)
        case ast.Name(n):
            return Var(n)
        case ast.BinOp(a, ast.Add(), b):
            return Add(_expr(a), _expr(b))
        case ast.BinOp(a, ast.Sub(), b):
            return Add(_expr(a), Neg(_expr(b)))
        case ast.BinOp(a, ast.Mult(), b):
            return Mul(_expr(a), _expr(b))
        case ast.BinOp(a, ast.Div(), b):
            return BinOp("/", _expr(a), _expr(b))
        case ast.UnaryOp(ast.USub(), a):
            return Neg(_expr(a))
        case ast.UnaryOp(ast.Not(), a):
            return UnOp("not", _expr(a))
        case ast.BoolOp(op, values):
            out = _expr(values[0])
            for v in values[1:]:
                out = BinOp("and" if isinstance(op, ast.And) else "or", out, _expr(v))
            return out
        case ast.Compare(a, [op], [b]):
            return BinOp(_COMPARE[type(op)], _expr(a), _expr(b))
        case ast.IfExp(t, a, b):
            return If(_expr(t), _expr(a), _expr(b))
        case ast.Subscript(a, f):
            return DynProj(_expr(a), _expr(f))
        case ast.Attribute(a, f):
            return Proj(_expr(a), f)
        case ast.List(items) | ast.Set(items):
            return SetLit(tuple(map(_expr, items)))
        case ast.Dict(ks, vs):
            return MapLit(tuple(map(_expr, ks)), tuple(map(_expr, vs)))
        case ast.DictComp(ast.Name(k), v, [ast.comprehension(ast.Name(x), over, [], 0)]) if k == x:
            return Tabulate(x, _expr(over), _expr(v))
        case ast.Call(ast.Name(m), [ast.GeneratorExp(v, [ast.comprehension(ast.Name(x), over, [], 0)])]) if m in _MONOID:
            return Fold(x, _expr(over), _expr(v), _MONOID[m])
        case ast.Call(ast.Name("keys"), [a]):
            return Keys(_expr(a))
        case ast.Call(f, [a]):
            return Lookup(_expr(f), _expr(a))
    raise SyntaxError(f"not in the language: {ast.unparse(e)}")
