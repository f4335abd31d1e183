"""What to learn over: relations, how they join, features and the label."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .typing import SchemaError


class CyclicJoin(ValueError):
    """The join has no join tree."""


@dataclass(frozen=True)
class Relation:
    """A bag of rows.  key with unique=True is declared to be unique; mult names an explicit multiplicity column."""

    name: str
    df: DataFrame
    key: tuple[str, ...] = ()
    unique: bool = False
    mult: str | None = None

    def checked(self) -> "Relation":
        """Verify the declared key by one job."""
        if self.unique and self.df.groupBy(*self.key).count().where("count > 1").take(1):
            raise SchemaError(f"{self.name}: {self.key} is not unique")
        return self


@dataclass(frozen=True)
class Feature:
    """expr is SQL over columns of its owner alone; scale: decimal digits that make it whole, for exact sums."""

    name: str
    owner: str
    expr: str
    kind: str = "cont"
    scale: int = 0

    @staticmethod
    def intercept(owner: str) -> "Feature":
        return Feature("1", owner, "1")

    def column(self, exact: bool = False, null_policy: str = "error") -> Column:
        c = F.expr(self.expr)
        if self.kind == "cat":
            return c
        if exact:
            c = F.round(c * 10**self.scale).cast("decimal(18,0)") if self.scale else c.cast("decimal(18,0)")
        else:
            c = c.cast("double")
        if null_policy == "error":
            return F.coalesce(c, F.raise_error(F.lit(f"NULL in feature {self.name}")).cast("decimal(18,0)" if exact else "double"))
        return F.coalesce(c, F.lit(0).cast("decimal(18,0)" if exact else "double")) if null_policy == "zero" else c


@dataclass(frozen=True)
class JoinSpec:
    """on: (left, right, ((left column, right column), ...)).  where: SQL conditions by relation.
    null_policy: error, drop (rows of a relation with a NULL feature go) or zero."""

    relations: dict[str, Relation]
    on: tuple = ()
    where: dict[str, str] = field(default_factory=dict)
    null_policy: str = "error"

    def rows(self, name: str) -> DataFrame:
        df = self.relations[name].df
        return df.where(self.where[name]) if name in self.where else df

    def filtered(self, **where: str) -> "JoinSpec":
        both = dict(self.where)
        for k, v in where.items():
            both[k] = f"({both[k]}) and ({v})" if k in both else v
        return replace(self, where=both)

    @staticmethod
    def natural(relations: list[Relation], **kw) -> "JoinSpec":
        """Edges from shared column names, by removing ears: a relation all of whose shared columns lie in one other."""
        left = {r.name: set(r.df.columns) for r in relations}
        edges = []
        while len(left) > 1:
            for name, cols in sorted(left.items(), key=lambda x: len(x[1])):
                shared = {c for c in cols if any(c in o for n, o in left.items() if n != name)}
                into = next((n for n, o in left.items() if n != name and shared and shared <= o), None)
                if into:
                    edges.append((into, name, tuple((c, c) for c in sorted(shared))))
                    del left[name]
                    break
            else:
                raise CyclicJoin(f"no ear among {sorted(left)}")
        return JoinSpec({r.name: r for r in relations}, tuple(edges), **kw)

    def check(self, features: list[Feature]) -> None:
        """Resolve every feature before any job starts."""
        for f in features:
            if f.owner not in self.relations:
                raise SchemaError(f"{f.name}: no relation {f.owner}")
            try:
                kind = self.relations[f.owner].df.select(F.expr(f.expr).alias("x")).schema["x"].dataType.simpleString()
            except Exception as e:
                raise SchemaError(f"{f.name}: {str(e).splitlines()[0]}") from e
            if f.kind == "cont" and kind in ("string", "timestamp", "timestamp_ntz", "binary"):
                raise SchemaError(f"{f.name} is {kind}, not a number")


@dataclass
class JoinTree:
    root: str
    children: dict[str, list[str]]
    edge: dict[str, tuple]  # child -> ((parent column, child column), ...)

    def below(self, name: str) -> set[str]:
        return {name}.union(*(self.below(c) for c in self.children[name])) if self.children[name] else {name}

    def parent(self, name: str) -> str | None:
        return next((p for p, cs in self.children.items() if name in cs), None)


def build_join_tree(spec: JoinSpec, root: str | None = None) -> JoinTree:
    """The join order is given by the edges; the root is the largest relation unless named."""
    if len(spec.on) != len(spec.relations) - 1:
        raise CyclicJoin(f"{len(spec.on)} edges between {len(spec.relations)} relations")
    if root is None:
        root = max(spec.relations, key=lambda n: (size_of(spec.relations[n].df), n))
    children: dict[str, list[str]] = {n: [] for n in spec.relations}
    edge, seen, open_ = {}, {root}, [root]
    while open_:
        at = open_.pop(0)
        for a, b, cols in spec.on:
            for p, c, pairs in ((a, b, cols), (b, a, tuple((r, l) for l, r in cols))):
                if p == at and c not in seen:
                    children[at].append(c)
                    edge[c] = tuple(pairs)
                    seen.add(c)
                    open_.append(c)
    if seen != set(spec.relations):
        raise CyclicJoin(f"{sorted(set(spec.relations) - seen)} can't be reached")
    return JoinTree(root, children, edge)


def size_of(df: DataFrame) -> int:
    """Bytes by the optimiser's statistics, which come from file sizes; no job."""
    return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
