"""Aggregates over a join, pushed past it: views per edge of the join tree, merged, in one pass per relation.

A monomial is a sorted tuple of feature names; the empty one is the count.  Restricted to a subtree it keeps the features
that the subtree owns; a subtree that owns none of them contributes its count.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce
from operator import mul

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..spec import Feature, JoinSpec, JoinTree, build_join_tree, size_of

Monomial = tuple[str, ...]


def monomials(names: list[str], degree: int = 2) -> list[Monomial]:
    """All up to that degree; the intercept's name "1" stands for no factor."""
    out: list[Monomial] = [()]
    for _ in range(degree):
        out += [tuple(sorted((*m, n))) for m in out for n in names if n != "1"]
    return sorted(set(out), key=lambda m: (len(m), m))


@dataclass
class ViewNode:
    """What one relation publishes to its parent: key, distinct values, carried group columns."""

    relation: str
    key: tuple[str, ...]
    values: list[Monomial]
    carried: list[str]
    children: list["ViewNode"] = field(default_factory=list)

    def walk(self):
        yield self
        for c in self.children:
            yield from c.walk()


def push_down(batch: list[Monomial], tree: JoinTree, owner: dict[str, str], groups: list[str] = []) -> ViewNode:
    """One view per edge for the given aggregates.  With one aggregate this is its own view tree; with a batch the views
    of a node are merged as they are made, since equal restrictions are one value."""

    def node(name: str, batch: list[Monomial]) -> ViewNode:
        kids = []
        for c in tree.children[name]:
            inside = tree.below(c)
            kids.append(node(c, list(dict.fromkeys(restrict(m, inside, owner) for m in batch))))
        key = tuple(c for _, c in tree.edge.get(name, ()))
        return ViewNode(name, key, batch, [g for g in groups if owner[g] in tree.below(name)], kids)

    return node(tree.root, list(dict.fromkeys(batch)))


def restrict(m: Monomial, inside: set[str], owner: dict[str, str]) -> Monomial:
    return tuple(f for f in m if owner[f] in inside)


def merge_views(trees: list[ViewNode]) -> ViewNode:
    """One tree whose nodes have all distinct values of the same nodes of the given trees."""
    first = trees[0]
    values = list(dict.fromkeys(v for t in trees for v in t.values))
    kids = [merge_views([t.children[k] for t in trees]) for k in range(len(first.children))]
    return ViewNode(first.relation, first.key, values, list(dict.fromkeys(c for t in trees for c in t.carried)), kids)


def product(cols: list[Column], exact: bool) -> Column:
    """Exact factors are at most 18 digits; a product is widened to 38 and checked."""
    return reduce(mul, cols) if cols else F.lit(1).cast("decimal(18,0)" if exact else "double")


@dataclass
class Emitted:
    df: DataFrame
    key: tuple[str, ...]
    value: dict[Monomial, Column]


class Emitter:
    def __init__(self, spec: JoinSpec, tree: JoinTree, features: list[Feature], exact: bool, join_hint: str | None = None):
        self.spec, self.tree, self.exact, self.hint = spec, tree, exact, join_hint
        self.by_name = {f.name: f for f in features}
        self.owner = {f.name: f.owner for f in features}

    def base(self, view: ViewNode) -> DataFrame:
        """The relation's own columns: join keys, features, multiplicity; nothing else is scanned."""
        name, rel = view.relation, self.spec.relations[view.relation]
        used = {f for m in view.values for f in m} | set(view.carried)
        own = [f for f in self.by_name.values() if f.owner == name and f.name in used]
        keys = dict.fromkeys([*view.key, *(p for c in view.children for p, _ in self.tree.edge[c.relation])])
        cols = [F.col(k).alias(f"k_{name}_{k}") for k in keys]
        cols += [f.column(self.exact, self.spec.null_policy).alias(f"f_{f.name}") for f in own]
        if rel.mult:
            cols.append(F.col(rel.mult).cast("decimal(18,0)" if self.exact else "double").alias(f"m_{name}"))
        df = self.spec.rows(name).select(*cols)
        if self.spec.null_policy == "drop" and own:
            df = df.where(reduce(lambda a, b: a & b, [F.col(f"f_{f.name}").isNotNull() for f in own]))
        return df

    def join(self, df: DataFrame, name: str, child: Emitted, child_name: str) -> DataFrame:
        right = child.df.hint(self.hint) if self.hint else child.df
        on = [F.col(f"k_{name}_{p}") == F.col(f"k_{child_name}_{c}") for p, c in self.tree.edge[child_name]]
        return df.join(right, reduce(lambda a, b: a & b, on))

    def local(self, name: str, m: Monomial) -> list[Column]:
        rel = self.spec.relations[name]
        return ([F.col(f"m_{name}")] if rel.mult else []) + [F.col(f"f_{f}") for f in m if self.owner[f] == name]

    def formula(self, view: ViewNode, kids: list[tuple[ViewNode, Emitted]], m: Monomial) -> Column:
        parts = self.local(view.relation, m)
        for k, e in kids:
            r = restrict(m, self.tree.below(k.relation), self.owner)
            if r or not e.one_each:
                parts.append(e.value[r])
        return product(parts, self.exact)

    def total(self, c: Column) -> Column:
        return F.sum(c.cast("decimal(38,0)") if self.exact else c)

    def node(self, view: ViewNode) -> Emitted:
        """View of a relation: its children's views are joined first, then one group-by holds all values.  Where the edge
        key is the relation's declared key there is one row per key already, and the view is a projection."""
        kids = [(c, self.node(c)) for c in view.children]
        df = self.base(view)
        for c, e in kids:
            df = self.join(df, view.relation, e, c.relation)
        rel = self.spec.relations[view.relation]
        key = [f"k_{view.relation}_{k}" for k in view.key]
        carried = [f"f_{g}" for g in view.carried]
        values = {m: self.formula(view, kids, m) for m in view.values}
        if rel.unique and set(rel.key) <= set(view.key) and not rel.mult:
            out = Emitted(df, view.key, values)
            out.one_each = all(e.one_each for _, e in kids)
            return out
        names = {m: f"v_{view.relation}_{i}" for i, m in enumerate(view.values)}
        out = Emitted(df.groupBy(*key, *carried).agg(*[self.total(values[m]).alias(names[m]) for m in view.values]), view.key, {m: F.col(n) for m, n in names.items()})
        out.one_each = False
        return out

    def root(self, view: ViewNode, groups: list[str]) -> DataFrame:
        kids = [(c, self.node(c)) for c in view.children]
        df = self.base(view)
        for c, e in kids:
            df = self.join(df, view.relation, e, c.relation)
        sums = [self.total(self.formula(view, kids, m)).alias(f"a{i}") for i, m in enumerate(view.values)]
        return df.groupBy(*[F.col(f"f_{g}").alias(g) for g in groups]).agg(*sums) if groups else df.agg(*sums)

    def nested(self, view: ViewNode, order: list[str] | None = None) -> DataFrame:
        """Root grouped by its edge keys first, then child after child is joined above the sums below it and the key of that
        child is summed away: each look-up happens once per key and not once per row.  Without an order, the children whose
        keys would hardly reduce the root's rows are looked up by row."""
        kids = {c.relation: (c, self.node(c)) for c in view.children}
        order = list(kids) if order is None else order
        return self.levels(view, kids, order, [c for c in kids if c not in order])

    def levels(self, view: ViewNode, kids: dict, order: list[str], by_rows: list[str]) -> DataFrame:
        """Look-ups by row for some children, then nested sums over the keys of the others."""
        name, df = view.relation, self.base(view)
        inside = {name}.union(*(self.tree.below(c) for c in by_rows))
        for c in by_rows:
            df = self.join(df, name, kids[c][1], c)
        keys = {c: [f"k_{name}_{p}" for p, _ in self.tree.edge[c]] for c in order}
        step, names = 0, {}
        for left in range(len(order), -1, -1):
            new = list(dict.fromkeys(restrict(m, inside, self.owner) for m in view.values))
            if not step:
                values = {m: product(self.local(name, m) + [kids[c][1].value[r] for c in by_rows if (r := restrict(m, self.tree.below(c), self.owner)) or not kids[c][1].one_each], self.exact) for m in new}
            else:
                c = order[left]
                df, below = self.join(df, name, kids[c][1], c), self.tree.below(c)
                values = {}
                for m in new:
                    inner, r = F.col(names[restrict(m, inside - below, self.owner)]), restrict(m, below, self.owner)
                    values[m] = inner * kids[c][1].value[r] if r or not kids[c][1].one_each else inner
            names = {m: f"n{step}_{i}" for i, m in enumerate(new)}
            sums = [self.total(values[m]).alias(names[m]) for m in new]
            by = list(dict.fromkeys(k for d in order[:left] for k in keys[d]))
            df = df.groupBy(*by).agg(*sums) if by else df.agg(*sums)
            step += 1
            if left:
                inside = inside | self.tree.below(order[left - 1])
        return df.select(*[F.col(names[m]).alias(f"a{i}") for i, m in enumerate(view.values)])


Emitted.one_each = False
PAYS = 8  # root rows that a group of keys should hold on average for a level of its own


def worthwhile(spec: JoinSpec, tree: JoinTree) -> list[str]:
    """Children of the root whose keys together leave at least PAYS rows a group, few keys first.  Numbers of keys and rows
    are taken from the optimiser's sizes, 32 bytes a row."""
    count = lambda n: max(1.0, size_of(spec.relations[n].df) / 32)
    out, groups = [], 1.0
    for n, c in sorted((count(c), c) for c in tree.children[tree.root]):
        groups *= n
        if groups * PAYS > count(tree.root):
            break
        out.append(c)
    return out


def naive_join(spec: JoinSpec, features: list[Feature], exact: bool = False, tree: JoinTree | None = None) -> DataFrame:
    """The joined rows: features by name, and __mult, the product of multiplicities."""
    tree = tree or build_join_tree(spec)
    em = Emitter(spec, tree, features, exact)
    view = push_down([tuple(sorted(f.name for f in features))], tree, em.owner)

    def walk(v: ViewNode) -> DataFrame:
        df = em.base(v)
        for c in v.children:
            df = em.join(df, v.relation, Emitted(walk(c), c.key, {}), c.relation)
        return df

    mults = [F.col(f"m_{n}") for n, r in spec.relations.items() if r.mult]
    return walk(view).select(*[F.col(f"f_{f.name}").alias(f.name) for f in features], product(mults, exact).alias("__mult"))


def set_number(names: list[str], group: tuple[str, ...]) -> int:
    """Spark's number of the grouping set `group` of the columns `names`: a bit for each column that is not in it."""
    return sum(1 << k for k, n in enumerate(reversed(names)) if n not in group)


def grouped_by_sets(df: DataFrame, names: list[str], sets: list[tuple[str, ...]], sums: list[Column]) -> DataFrame:
    """df grouped by each of the sets of columns in one pass, with __g, the number of a row's set."""
    return df.groupingSets([[F.col(n) for n in s] for s in sets], *[F.col(n) for n in names]).agg(F.grouping_id().alias("__g"), *sums)


STRATEGIES = ("materialised", "pushdown", "merged", "multi", "trie", "sorted", "hashed")


def aggregate(spec: JoinSpec, features: list[Feature], batch: list[Monomial], strategy: str = "multi", exact: bool = False, groups: list[str] = [], root: str | None = None, order: list[str] | None = None) -> DataFrame:
    """One row (or one per group) with a sum a0, a1, ... for each monomial of the batch, by the named strategy.

    pushdown: a view tree and a pass for each aggregate; merged: shared views, a pass for each aggregate; multi: shared
    views, one pass; trie: nested passes over the root; sorted, hashed: multi with merge or hash look-ups."""
    tree = build_join_tree(spec, root)
    hint = {"sorted": "merge", "hashed": "shuffle_hash"}.get(strategy)
    em = Emitter(spec, tree, features, exact, hint)
    if strategy == "materialised":
        joined = naive_join(spec, features, exact, tree)
        sums = [em.total(product([F.col("__mult"), *[F.col(f) for f in m]], exact)).alias(f"a{i}") for i, m in enumerate(batch)]
        return joined.groupBy(*groups).agg(*sums) if groups else joined.agg(*sums)
    if strategy in ("pushdown", "merged"):
        ones = passes(spec, features, batch, strategy, exact, groups, root)
        return reduce(lambda a, b: a.join(b, groups) if groups else a.crossJoin(b), ones)  # one row each
    view = push_down(batch, tree, em.owner, groups)
    if strategy == "trie":
        return em.nested(view, worthwhile(spec, tree) if order is None else order)
    return em.root(view, groups)


def passes(spec: JoinSpec, features: list[Feature], batch: list[Monomial], strategy: str, exact: bool = False, groups: list[str] = [], root: str | None = None) -> list[DataFrame]:
    """What aggregate() joins for pushdown and merged: the sum a0, a1, ... of each monomial by a pass of its own.  Run one after
    the other they need the shuffle files of one pass at a time."""
    tree = build_join_tree(spec, root)
    em = Emitter(spec, tree, features, exact)
    merged, out = push_down(batch, tree, em.owner, groups), []
    for i, m in enumerate(batch):
        view = push_down([m], tree, em.owner, groups)
        if strategy == "merged":  # the views hold all values; the root computes one
            view = ViewNode(merged.relation, merged.key, [m], merged.carried, merged.children)
        out.append(em.root(view, groups).withColumnRenamed("a0", f"a{i}"))
    return out


def batch_stats(spec: JoinSpec, features: list[Feature], batch: list[Monomial], root: str | None = None) -> dict:
    """Numbers of aggregates and views, before and after merging."""
    tree = build_join_tree(spec, root)
    owner = {f.name: f.owner for f in features}
    single = [push_down([m], tree, owner) for m in batch]
    merged = merge_views(single)
    return {"aggregates": len(batch), "distinct_aggregates": len(set(batch)), "views_separate": sum(len(list(t.walk())) - 1 for t in single), "views_merged": len(list(merged.walk())) - 1, "values_merged": sum(len(n.values) for n in merged.walk()) - len(merged.values)}


def view_keys(spec: JoinSpec, features: list[Feature], batch: list[Monomial], root: str | None = None) -> dict[str, int]:
    """Distinct keys of each relation's view, counted on the tables.  They do not depend on the view's values, so an aggregate's
    own view has as many as the merged one."""
    tree = build_join_tree(spec, root)
    em = Emitter(spec, tree, features, False)
    merged = push_down(batch, tree, em.owner)
    return {v.relation: em.node(v).df.agg(F.count_distinct(*[F.col(f"k_{v.relation}_{k}") for k in v.key])).first()[0] for v in merged.walk() if v is not merged}


def assign_roots(groups: list[list[str]], tree: JoinTree, owner: dict[str, str]) -> list[str]:
    """For each list of group keys the relation that owns most of them; the tree's root without any."""
    return [max(sorted({owner[g] for g in gs}), key=lambda r: sum(owner[g] == r for g in gs)) if gs else tree.root for gs in groups]
