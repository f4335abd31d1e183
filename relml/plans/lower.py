"""From programs to Spark: data-dependent sums become one batch of aggregates per round, collections become DataFrames."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..ir import BINDERS, Add, BinOp, Const, DynProj, Expr, FieldName, Fold, If, Iterate, Keys, Let, Lookup, MapLit, Mul, Neg, Proj, Rec, SetLit, Tabulate, UnOp, Var, Variant, children, free, interpret, rebuild

EXACT = "decimal(38,0)"
_BIN = {"==": lambda a, b: a == b, "!=": lambda a, b: a != b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b, "/": lambda a, b: a / b, "and": lambda a, b: a & b, "or": lambda a, b: a | b}
_UN = {"not": lambda a: ~a, "abs": F.abs, "sqrt": F.sqrt, "int": lambda a: a.cast("bigint"), "inv": lambda a: 1 / a}


def row_expr(e: Expr, row: str, table: str, env: dict, exact: bool = False, mult: str | None = None, bags: dict | None = None) -> Column:
    """Column for an expression over one row; what does not depend on the row is worked out on the driver."""

    def lit(v):
        return F.lit(str(v)).cast(EXACT) if exact and isinstance(v, int) and not isinstance(v, bool) else F.lit(v)

    def go(x: Expr, env: dict) -> Column:
        if row not in free(x) and free(x) <= set(env):
            return lit(interpret(x, env))
        match x:
            case Lookup(Var(t), Var(r)) if t == table and r == row:
                return F.col(mult).cast(EXACT) if mult and exact else F.col(mult) if mult else lit(1)
            case Lookup(Var(t), _) if bags and t in bags:
                return bags[t]
            case Proj(Var(r), f) if r == row:
                return F.col(f).cast(EXACT) if exact else F.col(f)
            case DynProj(Var(r), f) if r == row:
                name = interpret(f, env)
                return F.col(name).cast(EXACT) if exact else F.col(name)
            case Proj(Rec(names, values), f):
                return go(values[names.index(f)], env)
            case Proj(Variant(tag, a), f):
                return go(a, env) if tag == f else F.lit(None)
            case Add(a, b):
                return go(a, env) + go(b, env)
            case Mul(a, b):
                got = go(a, env) * go(b, env)
                return got.cast(EXACT) if exact else got
            case Neg(a):
                return -go(a, env)
            case BinOp(op, a, b) if op in _BIN:
                return _BIN[op](go(a, env), go(b, env))
            case UnOp(op, a):
                return _UN[op](go(a, env))
            case If(t, a, b):
                return F.when(go(t, env), go(a, env)).otherwise(go(b, env))
            case Let(v, a, b):
                from ..ir import substitute

                return go(substitute(b, v, a), env)
            case Fold(v, over, body, "sum"):
                return reduce(lambda p, q: p + q, [go(body, env | {v: item}) for item in interpret(over, env)])
        raise TypeError(f"no column for {x}")

    return go(e, env)


def is_data(e: Expr, table: str) -> bool:
    return isinstance(e, Keys) and e.arg == Var(table)


def extract_aggregates(e: Expr, table: str) -> tuple[list[Fold], Expr]:
    """Closed data-dependent sums of e, each under a name of its own, equal ones once, and e with the names instead."""
    found: dict[Expr, str] = {}

    def go(x: Expr, bound: frozenset) -> Expr:
        if isinstance(x, Fold) and is_data(x.over, table) and not free(x) & bound:
            key = Fold(x.var, x.over, _canonical(x.body), x.monoid)
            return Var(found.setdefault(key, f"agg{len(found)}"))
        var, inside = BINDERS.get(type(x), (None, ()))
        return rebuild(x, lambda f, c: go(c, bound | {getattr(x, var)} if f in inside else bound))

    rest = go(e, frozenset())
    return list(found), rest


def _canonical(e: Expr) -> Expr:
    """Factors of a product in one order, so x.a * x.b and x.b * x.a are one aggregate."""
    from ..ir import show
    from ..rewrite import factors, product

    return product(sorted(factors(e), key=show)) if isinstance(e, Mul) else e


def evaluate(program: Expr, table: str, df: DataFrame, env: dict | None = None, exact: bool = True, mult: str | None = None, log: list[int] | None = None):
    """Run a program whose data is df.  Each straight stretch is run twice: first to see which sums it needs, then, after one
    job for all of them, with their values.  log gets the number of sums of each job."""

    def stretch(e: Expr, env: dict):
        if not _touches(e, table):
            return interpret(e, env)
        columns: list[Column] = []
        walk(e, env, lambda c: columns.append(c) or 0)
        if log is not None:
            log.append(len(columns))
        values = list(df.agg(*[c.alias(f"a{i}") for i, c in enumerate(columns)]).first())
        got = iter([int(v or 0) if exact else float(v or 0) for v in values])
        return walk(e, env, lambda _: next(got))

    def walk(e: Expr, env: dict, ask):
        """The interpreter, with sums over the table answered by ask."""
        if isinstance(e, Fold) and is_data(e.over, table):
            c = row_expr(e.body, e.var, table, env, exact, mult)
            return ask(F.sum(c.cast(EXACT) if exact else c))
        match e:
            case Tabulate(v, over, body):
                return {i: walk(body, env | {v: i}, ask) for i in interpret(over, env)}
            case Let(v, a, b):
                return walk(b, env | {v: walk(a, env, ask)}, ask)
            case Rec(names, values):
                from ..ir import Record

                return Record(zip(names, [walk(x, env, ask) for x in values]))
            case Fold(v, over, body, "sum"):
                from ..ir import add

                return reduce(add, [walk(body, env | {v: i}, ask) for i in interpret(over, env)])
            case _ if _touches(e, table):
                new, names = {}, iter(range(1000))

                def hold(_, c: Expr) -> Expr:
                    n = f"__{next(names)}"
                    new[n] = walk(c, env, ask)
                    return Var(n)

                shell = rebuild(e, hold)
                return interpret(shell, env | new)
        return interpret(e, env)

    def run(e: Expr, env: dict):
        match e:
            case Let(v, a, b):
                return run(b, env | {v: run(a, env)})
            case Iterate(v, init, test, step, result):
                env = env | {v: run(init, env), "round": 0}
                while interpret(test, env):
                    env = env | {v: stretch(step, env), "round": env["round"] + 1}
                return run(result, env)
        return stretch(e, env)

    return run(program, env or {})


def _touches(e: Expr, table: str) -> bool:
    return table in free(e)


def lower(e: Expr, tables: dict[str, DataFrame]) -> DataFrame:
    """A collection-valued expression over bags as a DataFrame: keys with `value`, a set as its elements, or one row."""
    match e:
        case Keys(Var(t)):
            return tables[t].distinct()
        case Keys(a):
            got = lower(a, tables)
            return got.select(*[c for c in got.columns if c != "value"])
        case Add(a, b):
            x, y = lower(a, tables), lower(b, tables)
            keys = [c for c in x.columns if c != "value"]
            return x.unionByName(y).groupBy(*keys).agg(F.sum("value").alias("value"))
        case Let(v, a, b):
            return lower(b, tables | {v: lower(a, tables)})
        case Tabulate(k, Keys(keys), Fold(x, Keys(Var(t)), Mul(BinOp("==", left, right), body), "sum")):
            # a value per key: the test for the key is a group-by
            inner = right if k in free(left) else left
            names = lower(Keys(keys), tables).columns
            return lower(Fold(x, Keys(Var(t)), MapLit((Rec(tuple(names), (inner,)),), (body,))), tables)
        case Fold(x, Keys(Var(t)), body, m):
            df, bags = tables[t], {}
            for n, other in tables.items():
                for look in _lookups(body, n, x, t):
                    keys = look.key if isinstance(look.key, Rec) else Rec((other.columns[0],), (look.key,))
                    right = other.select(*[F.col(k).alias(f"__{n}_{k}") for k in keys.names], F.col("value").alias(f"__{n}_value"))
                    on = [row_expr(v, x, t, {}) == F.col(f"__{n}_{k}") for k, v in zip(keys.names, keys.values)]
                    df = df.join(right, reduce(lambda a, b: a & b, on))
                    bags[n] = F.col(f"__{n}_value")
            col = lambda b: row_expr(b, x, t, {}, bags=bags)
            if m in ("union",) and isinstance(body, SetLit):
                return df.select(col(body.items[0]).alias("element")).distinct()
            if isinstance(body, MapLit):
                key = body.keys[0] if isinstance(body.keys[0], Rec) else Rec(("key",), (body.keys[0],))
                return df.groupBy(*[col(v).alias(n) for n, v in zip(key.names, key.values)]).agg(F.sum(col(body.values[0])).alias("value"))
            if isinstance(body, Rec):
                return df.agg(*[F.sum(col(v)).alias(n) for n, v in zip(body.names, body.values)])
            fn = {"sum": F.sum, "min": F.min, "max": F.max, "any": F.bool_or, "all": F.bool_and}[m]
            return df.agg(fn(col(body)).alias("value"))
    raise TypeError(f"no DataFrame for {e}")


def _lookups(e: Expr, name: str, row: str, table: str) -> list[Lookup]:
    if isinstance(e, Lookup) and e.table == Var(name) and name != table:
        return [e]
    out: list[Lookup] = []
    for _, c in children(e):
        out += [x for x in _lookups(c, name, row, table) if x not in out]
    return out
