"""Types of the language and the check at the border of the two dialects."""

from __future__ import annotations

from dataclasses import dataclass

from .ir import Add, BinOp, Const, DynProj, Expr, FieldName, Fold, If, Iterate, Keys, Let, Lookup, MapLit, Mul, Neg, Proj, Rec, SetLit, Tabulate, UnOp, Var, Variant, show


class SchemaError(TypeError):
    """A field that does not exist, or values that can't be combined."""


@dataclass(frozen=True)
class Type:
    kind: str  # int real str bool enum field hot rec var map set
    args: tuple = ()

    def field(self, name: str) -> "Type":
        got = dict(self.args).get(name)
        if self.kind not in ("rec", "var") or got is None:
            raise SchemaError(f"no field {name} in {self}")
        return got


INT, REAL, STR, BOOL, FIELD = Type("int"), Type("real"), Type("str"), Type("bool"), Type("field")


def hot(n: int, of: Type) -> Type:
    """One-hot code: n reals indexed by a category."""
    return Type("hot", (n, of))


def rec(**f: Type) -> Type:
    return Type("rec", tuple(sorted(f.items())))


def map_of(k: Type, v: Type) -> Type:
    return Type("map", (k, v))


def set_of(t: Type) -> Type:
    return Type("set", (t,))


def joined(a: Type, b: Type, why: Expr) -> Type:
    if a == b:
        return a
    if {a.kind, b.kind} <= {"int", "real", "bool"}:
        return REAL if REAL in (a, b) else INT
    if a.kind == b.kind == "map" and a.args[0] == b.args[0]:
        return map_of(a.args[0], joined(a.args[1], b.args[1], why))
    if a.kind == b.kind == "rec" and [k for k, _ in a.args] == [k for k, _ in b.args]:
        return Type("rec", tuple((k, joined(x, y, why)) for (k, x), (_, y) in zip(a.args, b.args)))
    if a.kind in ("rec", "map", "hot") and b.kind in ("int", "real") and isinstance(why, Mul):
        return a
    if b.kind in ("rec", "map", "hot") and a.kind in ("int", "real") and isinstance(why, Mul):
        return b
    raise SchemaError(f"{a.kind} and {b.kind} in {show(why)[:120]}")


def typecheck(e: Expr, schema: dict[str, Type]) -> Type:
    """Type of a static expression; schema has the free variables' types.  Raises SchemaError before any job starts."""
    match e:
        case Const(v):
            return BOOL if isinstance(v, bool) else INT if isinstance(v, int) else REAL if isinstance(v, float) else STR
        case FieldName(_):
            return FIELD
        case Var(n):
            if n not in schema:
                raise SchemaError(f"unknown name {n}")
            return schema[n]
        case Add(a, b) | Mul(a, b):
            x, y = typecheck(a, schema), typecheck(b, schema)
            if "str" in (x.kind, y.kind) or "field" in (x.kind, y.kind):
                raise SchemaError(f"no arithmetic on text in {show(e)[:120]}")
            return joined(x, y, e)
        case Neg(a):
            return typecheck(a, schema)
        case UnOp(op, a):
            got = typecheck(a, schema)
            return BOOL if op == "not" else INT if op in ("size", "int") else REAL if op in ("sqrt", "inv") else got
        case BinOp(op, a, b):
            x, y = typecheck(a, schema), typecheck(b, schema)
            if op in ("==", "!=", "<", "<=", ">", ">="):
                joined(x, y, e)
                return BOOL
            return REAL if op == "/" else BOOL if op in ("and", "or", "in") else joined(x, y, e)
        case Fold(v, over, body, m):
            got = typecheck(body, schema | {v: element(typecheck(over, schema), over)})
            return got if m in ("sum", "min", "max", "bag", "union") else BOOL
        case Tabulate(v, over, body):
            k = element(typecheck(over, schema), over)
            return map_of(k, typecheck(body, schema | {v: k}))
        case SetLit(items):
            kinds = {typecheck(i, schema) for i in items}
            if len(kinds) > 1:
                raise SchemaError("a static set holds one type")
            return set_of(kinds.pop() if kinds else INT)
        case MapLit(ks, vs):
            k, v = {typecheck(i, schema) for i in ks}, {typecheck(i, schema) for i in vs}
            if len(k) > 1 or len(v) > 1:
                raise SchemaError("a static dictionary holds one type of key and of value")
            return map_of(k.pop(), v.pop())
        case Keys(a):
            return set_of(element(typecheck(a, schema), a))
        case Lookup(t, k):
            got = typecheck(t, schema)
            if got.kind != "map":
                raise SchemaError(f"look-up in {got.kind}")
            joined(got.args[0], typecheck(k, schema), e)
            return got.args[1]
        case Rec(names, values):
            return Type("rec", tuple(sorted(zip(names, [typecheck(v, schema) for v in values]))))
        case Variant(tag, a):
            return Type("var", ((tag, typecheck(a, schema)),))
        case Proj(a, f):
            return typecheck(a, schema).field(f)
        case DynProj(_, f):
            raise SchemaError(f"field name known only at run time: {show(f)}")
        case Let(v, a, b):
            return typecheck(b, schema | {v: typecheck(a, schema)})
        case If(t, a, b):
            if typecheck(t, schema).kind != "bool":
                raise SchemaError("test is not a truth value")
            return joined(typecheck(a, schema), typecheck(b, schema), e)
        case Iterate(v, init, test, step, result):
            inner = schema | {v: typecheck(init, schema), "round": INT}
            typecheck(test, inner)
            inner[v] = joined(inner[v], typecheck(step, inner), e)
            return typecheck(result, inner)
    raise TypeError(e)


def element(t: Type, e: Expr) -> Type:
    if t.kind in ("map", "set"):
        return t.args[0]
    if t.kind == "rec":
        return FIELD
    raise SchemaError(f"{show(e)} is no collection")


def of_spark(schema) -> Type:
    """Bag of records for a StructType."""
    from pyspark.sql import types as T

    def one(t) -> Type:
        if isinstance(t, (T.LongType, T.IntegerType, T.ShortType, T.ByteType)):
            return INT
        if isinstance(t, (T.DoubleType, T.FloatType, T.DecimalType)):
            return REAL
        return BOOL if isinstance(t, T.BooleanType) else STR

    return map_of(Type("rec", tuple(sorted((f.name, one(f.dataType)) for f in schema.fields))), INT)
