"""From a program over joined rows to one batch of pushed-down sums and a compiled loop.

The program (feature query and training loop in one) goes through the rewrite phases; the sums over the data that remain
are extracted as monomials and answered by any strategy of `plans.views` on the base relations; what is left touches no
data, and its loop step becomes straight-line Python.  Where a phase can't take a sum out of the loop (as with more features
than rows, where loops keep their order), the sums of a round are asked from the stored join, round by round.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from .. import frontend, rewrite
from ..ir import Add, Const, DynProj, Expr, FieldName, Fold, Iterate, Keys, Let, Lookup, Mul, Neg, Proj, Rec, Record, SetLit, Tabulate, Var, free, interpret, show
from ..spec import Feature, JoinSpec
from .lower import evaluate, extract_aggregates, is_data
from .views import Monomial, aggregate, build_join_tree, naive_join, push_down

ONE = "one"  # a program's name for the intercept


def monomial_of(e: Fold) -> Monomial | None:
    """The features of sum(Q(x) * x.a * x.b); None if the sum has another form."""
    names, counted = [], 0
    for f in rewrite.factors(e.body):
        match f:
            case Lookup(Var(t), Var(v)) if Keys(Var(t)) == e.over and v == e.var:
                counted += 1
            case Proj(Var(v), n) | DynProj(Var(v), FieldName(n)) if v == e.var:
                names.append(n)
            case _:
                return None
    return tuple(sorted(n for n in names if n != ONE)) if counted == 1 else None


@dataclass
class Compiled:
    """stages: the program after each phase.  batch: the distinct monomials; asked: the one behind each name agg0, agg1, ...
    of rest."""

    stages: dict[str, Expr]
    table: str
    spec: JoinSpec
    features: list[Feature]
    batch: list[Monomial] = field(default_factory=list)
    asked: list[Monomial] = field(default_factory=list)
    rest: Expr | None = None
    residual: bool = False

    def sums(self, strategy: str = "multi", exact: bool = False) -> DataFrame:
        """The one job that touches data."""
        return aggregate(self.spec, self.features, self.batch, strategy, exact)

    def run(self, env: dict, strategy: str = "multi", exact: bool = False, compiled: bool = True):
        if self.residual:
            rows = naive_join(self.spec, self.features, exact).persist()
            try:
                return evaluate(self.stages["normalised"], self.table, _with_one(rows, self.features), env, exact, "__mult")
            finally:
                rows.unpersist()
        got = dict(zip(self.batch, self.sums(strategy, exact).first() if self.batch else []))
        env = env | {f"agg{i}": (int(got[m] or 0) if exact else float(got[m] or 0)) for i, m in enumerate(self.asked)}
        return run_program(self.rest, env) if compiled else interpret(self.rest, env)

    def explain(self, stage: str | None = None, strategy: str = "multi", exact: bool = False) -> str:
        """The program after a phase; for `views` what each relation publishes, for `spark` the plan of the job."""
        if stage == "views":
            tree = build_join_tree(self.spec)
            view = push_down(self.batch, tree, {f.name: f.owner for f in self.features})
            return "\n".join(f"{v.relation}{list(v.key)}: " + ", ".join("*".join(m) or "count" for m in v.values) for v in view.walk())
        if stage == "spark":
            return self.sums(strategy, exact)._jdf.queryExecution().toString()
        if stage == "sums":
            return "\n".join("*".join(m) or "count" for m in self.batch)
        named = [stage] if stage else list(self.stages)
        return "\n".join(f"{n}: {show(self.stages[n])}" for n in named)


def _with_one(df: DataFrame, features: list[Feature]) -> DataFrame:
    from pyspark.sql import functions as F

    return df if any(f.name == ONE for f in features) else df.withColumn(ONE, F.lit(1))


def compile_program(program: Expr | str | Callable, spec: JoinSpec, features: list[Feature], table: str = "Q", rows: float = float("inf")) -> Compiled:
    """program: source text, a function to be read, or an expression whose variable `table` is the joined rows.  rows: an
    upper bound of their number, if one is known."""
    if isinstance(program, str):
        program = frontend.program_of(program)
    elif not isinstance(program, Expr):
        program = frontend.program(program)
    stages = rewrite.stages(program, lambda e: len(e.items) if isinstance(e, SetLit) else rows, lambda e: is_data(e, table))
    found, rest = extract_aggregates(stages["specialised"], table)
    batch = [monomial_of(f) for f in found]
    out = Compiled(stages, table, spec, [f for f in features if f.name != ONE], list(dict.fromkeys(batch)), batch, rest)
    known = {f.name for f in features} | {ONE}
    if table in free(rest) or any(m is None or not set(m) <= known for m in batch):
        out.batch, out.asked, out.rest, out.residual = [], [], None, True
    return out


# --- the loop, compiled


class NotCompiled(ValueError):
    """An expression that straight-line arithmetic can't say."""


def compile_step(step: Expr, var: str, keys: list, env: dict) -> Callable[[list], list]:
    """The step of a loop over a record of numbers as one Python function from a list to a list: the domain is unrolled,
    look-ups are places, and what doesn't depend on the loop variable is worked out once and bound as a constant."""
    place, constants = {k: i for i, k in enumerate(keys)}, []

    def emit(e: Expr, env: dict) -> str:
        if free(e) <= env.keys():
            value = interpret(e, env)
            if isinstance(value, (int, float)) and not isinstance(value, bool):
                constants.append(value)
                return f"c[{len(constants) - 1}]"
        match e:
            case Lookup(Var(v), k) | DynProj(Var(v), k) if v == var and free(k) <= env.keys():
                return f"t[{place[interpret(k, env)]}]"
            case Proj(Var(v), f) if v == var:
                return f"t[{place[f]}]"
            case Add(a, b):
                return f"({emit(a, env)} + {emit(b, env)})"
            case Mul(a, b):
                return f"({emit(a, env)} * {emit(b, env)})"
            case Neg(a):
                return f"(-{emit(a, env)})"
            case Let(v, a, b):
                if free(a) <= env.keys():
                    return emit(b, env | {v: interpret(a, env)})
                from ..ir import substitute

                return emit(substitute(b, v, a), env)
            case Fold(v, over, body, "sum") if free(over) <= env.keys():
                return "(" + (" + ".join(emit(body, env | {v: i}) for i in interpret(over, env)) or "0") + ")"
        raise NotCompiled(show(e))

    def values(e: Expr, env: dict) -> list[str]:
        match e:
            case Let(v, a, b) if free(a) <= env.keys():
                return values(b, env | {v: interpret(a, env)})
            case Rec(names, items) if set(names) == set(keys):
                return [emit(items[names.index(k)], env) for k in keys]
            case Tabulate(v, over, body) if free(over) <= env.keys():
                return [emit(body, env | {v: k}) for k in keys]
        raise NotCompiled(show(e))

    scope: dict = {"c": constants}
    exec(f"def step(t):\n    return [{', '.join(values(step, dict(env)))}]", scope)  # noqa: S102  built from the expression above
    return scope["step"]


def run_program(e: Expr, env: dict):
    """Value of a program without data; loops whose step is straight-line run compiled."""
    match e:
        case Let(v, a, b):
            return run_program(b, env | {v: run_program(a, env)})
        case Iterate(v, init, test, step, result):
            start = run_program(init, env)
            keys = list(start.names()) if isinstance(start, Record) else list(start) if isinstance(start, dict) else None
            if keys is None or v in free(test):
                return interpret(e, env)
            try:
                once = compile_step(step, v, keys, env)
            except NotCompiled:
                return interpret(e, env)
            state, n = [interpret(Lookup(Var(v), FieldName(k)), {v: start}) for k in keys], 0
            while interpret(test, env | {"round": n}):
                state, n = once(state), n + 1
            return run_program(result, env | {v: dict(zip(keys, state)), "round": n})
    return interpret(e, env)


def least_squares(features: list[str], label: str) -> str:
    """Source of batch gradient descent over joined rows; A is the step factor, R the number of rounds, T0 the start."""
    names = ", ".join(f'"{f}"' for f in features)
    return f"""
F = [{names}]
N = sum(Q(x) for x in keys(Q))
theta = T0
while round < R:
    theta = {{f1: theta(f1) - A / N * sum(Q(x) * (sum(theta(f2) * x[f2] for f2 in F) - x.{label}) * x[f1] for x in keys(Q)) for f1 in F}}
return theta
"""
