"""Regression and classification trees by level: one batch of aggregates per depth for all open nodes.

A node's path is a conjunction of tests, each on one relation's feature, so it splits into a mask per relation.  The masks
meet along the join, the root's rows are summed by node and by the key of each branch before that branch's values are met,
and each value's sums end as rows (node, feature, value, sums).  All sums are over the inner join: rows without partners are
out, repeated keys, filters and multiplicities count.  Splits are found by running sums over the values; the other side is
the total less that.

Where values are binned and all keys below the root are unique, relations are held as keys and bins of a few bytes, a level
looks the bins of a row's partners up and counts them by node within its task (Looked).  No joined row is stored.
"""

from __future__ import annotations

import json
from bisect import bisect_left
from dataclasses import dataclass, field
from functools import cached_property, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Row, SparkSession, Window
from pyspark.sql import functions as F

from ..spec import Feature, JoinSpec, JoinTree, build_join_tree


@dataclass
class Node:
    node_id: int
    depth: int
    n: float
    prediction: float
    cost: float
    parent: int | None = None
    feature: str | None = None
    op: str | None = None
    threshold: float | None = None
    categories: list[str] | None = None
    sums: tuple = ()


@dataclass
class TreeModel:
    nodes: dict[int, Node] = field(default_factory=dict)

    def test(self, node: Node, column=lambda n: F.col(n)) -> Column:
        c = column(node.feature)
        return c.isin(node.categories) if node.op == "in" else c <= F.lit(node.threshold)

    def column(self, at: int = 1) -> Column:
        node = self.nodes[at]
        if node.feature is None:
            return F.lit(float(node.prediction))
        return F.when(self.test(node), self.column(2 * at)).otherwise(self.column(2 * at + 1))

    def predict(self, df: DataFrame, out: str = "prediction") -> DataFrame:
        return df.withColumn(out, self.column())

    def rows(self) -> list[tuple]:
        return [(k.node_id, k.depth, k.feature, k.op, k.threshold, ",".join(k.categories) if k.categories else None, float(k.n), float(k.prediction), k.parent) for _, k in sorted(self.nodes.items())]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows(), "node_id int, depth int, feature string, op string, threshold double, categories string, n double, prediction double, parent int")

    def sse(self) -> float:
        return sum(k.cost for k in self.nodes.values() if k.feature is None)

    def save(self, spark: SparkSession, path: str) -> None:
        spark.createDataFrame([(json.dumps([k.__dict__ for k in self.nodes.values()]),)], "tree string").coalesce(1).write.mode("overwrite").parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> "TreeModel":
        return TreeModel({k["node_id"]: Node(**k) for k in json.loads(spark.read.parquet(path).first().tree)})


class Measure:
    """Sums that a node needs, their cost and its prediction."""

    def __init__(self, kind: str, classes: int = 0):
        self.kind, self.classes = kind, classes

    def columns(self, y: Column, weight: Column) -> list[Column]:
        if self.kind == "sse":
            return [weight, weight * y, weight * y * y]
        return [weight, *[F.when(y == k, weight).otherwise(F.lit(0.0)) for k in range(self.classes)]]

    def arrays(self, y: np.ndarray, weight: np.ndarray) -> list[np.ndarray]:
        """columns, of arrays."""
        if self.kind == "sse":
            return [weight, weight * y, weight * y * y]
        return [weight, *[np.where(y == k, weight, 0.0) for k in range(self.classes)]]

    def cost(self, s: list[Column]) -> Column:
        if self.kind == "sse":
            return s[2] - s[1] * s[1] / s[0]
        if self.kind == "gini":
            return s[0] - reduce(lambda a, b: a + b, [c * c for c in s[1:]]) / s[0]
        return reduce(lambda a, b: a + b, [F.when(c > 0, -c * F.log(c / s[0])).otherwise(F.lit(0.0)) for c in s[1:]])

    def cost_of(self, s) -> float:
        import math

        if not s[0]:
            return 0.0
        if self.kind == "sse":
            return s[2] - s[1] * s[1] / s[0]
        if self.kind == "gini":
            return s[0] - sum(c * c for c in s[1:]) / s[0]
        return -sum(c * math.log(c / s[0]) for c in s[1:] if c > 0)

    def prediction(self, s) -> float:
        if not s[0]:
            return 0.0
        return s[1] / s[0] if self.kind == "sse" else float(max(range(self.classes), key=lambda k: (s[k + 1], -k)))

    def order(self, s: list[Column]) -> Column:
        """Categories in order of mean label; of their share of the last class in classification."""
        return s[1] / s[0] if self.kind == "sse" else s[-1] / s[0]


LOT = 60  # open nodes of one batch of sums: a node is a bit of a long
BLOCKS = 64  # parts into which the values of one feature are cut for their running sums


class Grower:
    """Grows a tree on the join.  past: trees of earlier rounds with their rates, whose predictions leave the label.

    A joined row's node follows from its tests in all relations, so each relation gives its rows a mask: bit j says that the
    tests on the path of open node j that are its own hold.  A branch publishes, for each edge key and mask, the number of
    joined rows below; rows that find no partner leave, and repeated keys count as often as they join.  Past trees have
    masks of their own, a bit for each leaf."""

    def __init__(self, spec: JoinSpec, features: list[Feature], label: Feature, measure: Measure, max_bins: int | None = None, past: list[tuple[float, TreeModel]] = ()):
        spec.check([*features, label])
        self.spec, self.features, self.label, self.measure, self.past = spec, features, label, measure, list(past)
        self.tree: JoinTree = build_join_tree(spec, label.owner)
        self.width = 3 if measure.kind == "sse" else 1 + measure.classes
        self.owner = {f.name: f.owner for f in features}
        self.bins: dict[str, list[float]] = {}
        self.blocks: dict[int, list[float]] = {}
        cont = [(k, f) for k, f in enumerate(features) if f.kind == "cont"]
        parts = max_bins or BLOCKS
        for rel in spec.relations:
            own = [(k, f) for k, f in cont if f.owner == rel]
            if own:
                got = quantiles(spec.rows(rel).select(*[f.column(False, spec.null_policy).alias(f.name) for _, f in own]), parts)
                for k, f in own:
                    edges = got[f.name]
                    if max_bins:
                        self.bins[f.name] = edges
                    else:
                        self.blocks[k] = edges
        self.held: DataFrame | None = None
        self.made: dict[str, DataFrame] = {}
        unique = all(map(self.all_unique, self.tree.children[self.tree.root]))
        self.looked = Looked(self) if self.bounded() and unique and not self.past else None
        if max_bins and not self.looked:  # binned once
            for df in self.base.values():
                df.persist()

    @cached_property
    def base(self) -> dict[str, DataFrame]:
        return {name: self.prepared(name) for name in self.spec.relations}

    def let_go(self) -> None:
        if self.held is not None:
            self.held.unpersist()
            self.held = None

    def close(self) -> None:
        self.let_go()
        if self.looked:
            self.looked.close()
        else:
            for df in self.base.values():
                df.unpersist()

    def binned(self, f: Feature) -> str:
        """SQL of the least edge that is not below the feature's value, by halving."""
        c = f"`f_{f.name}`"

        def search(edges: list[float]) -> str:
            if len(edges) == 1:
                return f"CASE WHEN {c} <= {edges[0]!r}D THEN {edges[0]!r}D ELSE {c} END"
            mid = len(edges) // 2
            return f"CASE WHEN {c} <= {edges[mid - 1]!r}D THEN {search(edges[:mid])} ELSE {search(edges[mid:])} END"

        return f"{search(self.bins[f.name])} AS {c}" if self.bins.get(f.name) else c

    def plain(self, name: str) -> DataFrame:
        """A relation's keys, features, weight and, at the root, the label."""
        own, rel = [f for f in self.features if f.owner == name], self.spec.relations[name]
        keys = dict.fromkeys([*(c for _, c in self.tree.edge.get(name, ())), *(p for c in self.tree.children[name] for p, _ in self.tree.edge[c])])
        cols = [F.col(k).alias(f"k_{name}_{k}") for k in keys] + [f.column(False, self.spec.null_policy).alias(f"f_{f.name}") for f in own]
        cols.append((F.col(rel.mult).cast("double") if rel.mult else F.lit(1.0)).alias(f"w_{name}"))
        if name == self.tree.root:
            cols.append(self.label.column(False, self.spec.null_policy).alias("y"))
        out = self.spec.rows(name).select(*cols)
        if self.spec.null_policy == "drop":
            out = out.dropna(subset=[f"f_{f.name}" for f in own] + (["y"] if name == self.tree.root else []))
        return out

    def prepared(self, name: str) -> DataFrame:
        """plain, with values cut to bins."""
        out, by = self.plain(name), {f"f_{f.name}": f for f in self.features if f.owner == name}
        return out.selectExpr(*[self.binned(by[c]) if c in by else f"`{c}`" for c in out.columns]) if self.bins else out

    def masks(self, name: str, open_: list[tuple[TreeModel, dict[int, int]]]) -> list[Column]:
        """For each tree the bits of the nodes whose tests in this relation hold; each test is worked out once."""
        def walk(model: TreeModel, bits: dict[int, int], at: int) -> Column | int:
            if at in bits:
                return 1 << bits[at]
            node = model.nodes.get(at)
            if node is None or node.feature is None:
                return 0
            left, right = walk(model, bits, 2 * at), walk(model, bits, 2 * at + 1)
            if self.owner[node.feature] == name:
                return left if left is right else F.when(model.test(node, lambda n: F.col(f"f_{n}")), as_column(left)).otherwise(as_column(right))
            if isinstance(left, int) and isinstance(right, int):
                return left | right
            return as_column(left).bitwiseOR(as_column(right))

        return [as_column(walk(model, bits, 1)) for model, bits in open_]

    def joined_on(self, left: str, right: str) -> Column:
        return reduce(lambda a, b: a & b, [F.col(f"k_{left}_{p}") == F.col(f"k_{right}_{c}") for p, c in self.tree.edge[right]])

    def entries(self, name: str, open_: list) -> DataFrame:
        """A relation's rows with, for each branch below, the masks m{j}_{branch} and the count n_{branch} of its rows, and
        the masks m{j}_{name} of both."""
        if name in self.made:  # once for its view, once for its values
            return self.made[name]
        df = self.base[name].select("*", *[m.alias(f"o{j}") for j, m in enumerate(self.masks(name, open_))])
        for c in self.tree.children[name]:
            df = df.join(self.view(c, open_), self.joined_on(name, c))
        both = [reduce(lambda a, c: a.bitwiseAND(F.col(f"m{j}_{c}")), self.tree.children[name], F.col(f"o{j}")).alias(f"m{j}_{name}") for j in range(len(open_))]
        kept = [c for c in df.columns if c not in {f"o{j}" for j in range(len(open_))}]
        self.made[name] = df.select(*kept, *both).where(f"m0_{name} <> 0")
        return self.made[name]

    def view(self, name: str, open_: list) -> DataFrame:
        """(edge key, masks, n): how many joined rows the branch has for each key and mask."""
        keys = [F.col(f"k_{name}_{c}") for _, c in self.tree.edge[name]]
        masks = [F.col(f"m{j}_{name}") for j in range(len(open_))]
        rows, n = self.entries(name, open_), self.within(name).alias(f"n_{name}")
        rel = self.spec.relations[name]
        if rel.unique and set(rel.key) <= {c for _, c in self.tree.edge[name]}:
            return rows.select(*keys, *masks, n) if self.all_unique(name) else rows.groupBy(*keys, *masks).agg(F.sum(n).alias(f"n_{name}"))
        return rows.groupBy(*keys, *masks).agg(F.sum(n).alias(f"n_{name}"))

    def all_unique(self, name: str) -> bool:
        """Whether each key of the branch has one row at most: then its view needs no grouping."""
        rel = self.spec.relations[name]
        return rel.unique and set(rel.key) <= {c for _, c in self.tree.edge[name]} and all(map(self.all_unique, self.tree.children[name]))

    def within(self, name: str, but: str | None = None) -> Column:
        """Weight of a row with the counts of its branches."""
        return reduce(lambda a, c: a * F.col(f"n_{c}"), [c for c in self.tree.children[name] if c != but], F.col(f"w_{name}"))

    def statistics(self, model: TreeModel | None = None, nodes: list[int] = (1,), totals: bool = False) -> DataFrame:
        """(node, fid, val, cat, s0, s1, ...) for all features and the given open nodes of model, LOT at most; with totals
        also a row of fid -1 for each node."""
        if len(nodes) > LOT or any(len(leaves(m)) > LOT for _, m in self.past):
            raise ValueError(f"more than {LOT} nodes")
        open_ = [(model or TreeModel(), {n: k for k, n in enumerate(nodes)})] + [(m, {n: k for k, n in enumerate(leaves(m))}) for _, m in self.past]
        root, self.made = self.tree.root, {}
        df = self.entries(root, open_)

        def place(j: int) -> Column:
            return F.round(F.log2(F.col(f"m{j}_{root}").cast("double"))).cast("int") + 1

        node = F.element_at(F.array(*map(F.lit, nodes)), place(0)).alias("node")
        y = F.col("y")
        for j, (rate, m) in enumerate(self.past, 1):
            y = y - F.element_at(F.array(*[F.lit(rate * m.nodes[n].prediction) for n in leaves(m)]), place(j))
        gone = {"y", *[f"m{j}_{root}" for j in range(len(open_))]}
        sums = self.measure.columns(y, F.lit(1.0))
        df = df.select(*[c for c in df.columns if c not in gone], node, *[c.alias(f"s{i}") for i, c in enumerate(sums)])
        if any(f.owner != root for f in self.features):  # read once for each branch
            self.held = df.persist()
        parts: list[DataFrame] = []
        self.descend(root, df, parts, open_, totals)
        every = reduce(lambda a, b: a.union(b), parts)
        return every.groupBy("node", "fid", "val", "cat").agg(*[F.sum(f"s{i}").alias(f"s{i}") for i in range(self.width)])

    def descend(self, name: str, df: DataFrame, parts: list[DataFrame], open_: list, totals: bool = False) -> None:
        """df: entries of a relation with their node and s0, s1, ..., sums over what is joined above them."""
        s = [f"s{i}" for i in range(self.width)]
        own = [(k, f) for k, f in enumerate(self.features) if f.owner == name]
        slots = [f"named_struct('fid', {k}, 'val', CAST(NULL AS DOUBLE), 'cat', CAST(`f_{f.name}` AS STRING))" if f.kind == "cat" else f"named_struct('fid', {k}, 'val', `f_{f.name}`, 'cat', CAST(NULL AS STRING))" for k, f in own]
        if totals:
            slots.append("named_struct('fid', -1, 'val', CAST(NULL AS DOUBLE), 'cat', CAST(NULL AS STRING))")
        if slots:
            each = df.select("node", *[(F.col(c) * self.within(name)).alias(c) for c in s], F.expr(f"explode(array({', '.join(slots)}))").alias("x"))
            parts.append(each.select("node", F.col("x.fid").alias("fid"), F.col("x.val").alias("val"), F.col("x.cat").alias("cat"), *s))
        for c in self.tree.children[name]:
            if any(f.owner in self.tree.below(c) for f in self.features):
                keys = [f"k_{name}_{p}" for p, _ in self.tree.edge[c]]
                masks = [f"m{j}_{c}" for j in range(len(open_))]
                less = df.groupBy("node", *[F.col(k) for k in keys], *[F.col(m).alias(f"up_{m}") for m in masks]).agg(*[F.sum(F.col(x) * self.within(name, c)).alias(x) for x in s])
                same = reduce(lambda a, b: a & b, [F.col(f"up_{m}") == F.col(m) for m in masks], self.joined_on(name, c))
                self.descend(c, less.join(self.entries(c, open_), same), parts, open_)

    def best_splits(self, stats: DataFrame, min_rows: int = 1) -> DataFrame:
        """(node, fid, op, val, categories, cost, l0.., t0..): the best test of each node.  Ties: feature, then value.

        Running sums are taken within blocks of values and lifted by the totals of the blocks before, so that no task holds
        all values of a feature; categories, in order of mean label, are one block."""
        n, cats = range(self.width), [k for k, f in enumerate(self.features) if f.kind == "cat"]
        s = [F.col(f"s{i}") for i in n]
        stats = stats.where("fid >= 0").withColumn("key", F.when(F.col("fid").isin(cats), self.measure.order(s)).otherwise(F.col("val")) if cats else F.col("val"))
        block = F.lit(0)
        if self.blocks:
            edges = stats.sparkSession.createDataFrame(sorted(self.blocks.items()), "fid int, edges array<double>")
            stats = stats.join(F.broadcast(edges), "fid", "left")  # BLOCKS numbers a feature
            block = F.coalesce(F.size(F.filter("edges", lambda e: e < F.col("val"))), F.lit(0))
        stats = stats.select("node", "fid", "val", "cat", "key", block.alias("block"), *s)
        each = stats.groupBy("node", "fid", "block").agg(*[F.sum(f"s{i}").alias(f"s{i}") for i in n])
        group = Window.partitionBy("node", "fid")
        past = group.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
        each = each.select("node", "fid", "block", *[F.coalesce(F.sum(f"s{i}").over(past), F.lit(0.0)).alias(f"b{i}") for i in n], *[F.sum(f"s{i}").over(group).alias(f"t{i}") for i in n])
        run = Window.partitionBy("node", "fid", "block").orderBy("key", "cat").rowsBetween(Window.unboundedPreceding, 0)
        rows = stats.select("node", "fid", "block", "val", "cat", "key", *[F.sum(f"s{i}").over(run).alias(f"r{i}") for i in n]).join(each, ["node", "fid", "block"])
        rows = rows.select("node", "fid", "val", "cat", "key", *[(F.col(f"b{i}") + F.col(f"r{i}")).alias(f"l{i}") for i in n], *[f"t{i}" for i in n])
        rows = rows.where((F.col("l0") >= min_rows) & (F.col("t0") - F.col("l0") >= min_rows))
        left, right = [F.col(f"l{i}") for i in n], [F.col(f"t{i}") - F.col(f"l{i}") for i in n]
        rows = rows.withColumn("cost", self.measure.cost(left) + self.measure.cost(right))
        best = rows.groupBy("node").agg(F.min(F.struct("cost", "fid", "key", "cat", "val", *[f"l{i}" for i in n], *[f"t{i}" for i in n])).alias("x")).select("node", "x.*")
        if not cats:
            return best.withColumn("categories", F.lit(None).cast("array<string>"))
        won = best.where(F.col("fid").isin(cats)).select(F.col("node").alias("n2"), F.col("fid").alias("f2"), F.struct("key", "cat").alias("last"))
        sets = stats.join(won, (F.col("node") == F.col("n2")) & (F.col("fid") == F.col("f2")) & (F.struct("key", "cat") <= F.col("last"))).groupBy("node").agg(F.collect_list("cat").alias("categories"))
        return best.join(sets, "node", "left")

    def bounded(self) -> bool:
        """Whether statistics are bounded by nodes, features and bins, whatever the data."""
        return bool(self.bins) and all(f.kind == "cont" and self.bins.get(f.name) for f in self.features)

    def chosen(self, stats: list, min_rows: int) -> dict:
        """best_splits on collected rows, for bounded statistics; by node, as namespaces."""
        from types import SimpleNamespace

        groups: dict[tuple[int, int], list] = {}
        for r in stats:
            if r.fid >= 0:
                groups.setdefault((r.node, r.fid), []).append(r)
        out: dict[int, SimpleNamespace] = {}
        for (node, fid), rows in sorted(groups.items()):
            rows.sort(key=lambda r: r.val)
            total = [float(sum(r[f"s{i}"] for r in rows)) for i in range(self.width)]
            left = [0.0] * self.width
            for r in rows:
                left = [l + r[f"s{i}"] for i, l in enumerate(left)]
                right = [t - l for t, l in zip(total, left)]
                if left[0] < min_rows or right[0] < min_rows:
                    continue
                cost = self.measure.cost_of(left) + self.measure.cost_of(right)
                if node not in out or cost < out[node].cost:
                    out[node] = SimpleNamespace(fid=fid, val=r.val, cost=cost, categories=None, left=left)
        return out

    def grow(self, max_depth: int, min_rows: int, min_gain: float = 1e-9) -> TreeModel:
        model, open_ = TreeModel(), [1]
        for depth in range(max_depth + 1):
            found, totals = {}, {}
            most = self.looked.lot() if self.looked else LOT
            for lo in range(0, len(open_), most):
                if depth == max_depth and model.nodes:
                    break
                lot = open_[lo : lo + most]
                stats = None if self.looked else self.statistics(model, lot, totals=not model.nodes)
                rows = self.looked.statistics(model, lot) if self.looked else stats.collect() if self.bounded() else None
                if rows is None:
                    stats.persist()
                if not model.nodes:
                    r = next((r for r in rows if r.fid == -1), None) if rows is not None else stats.where("fid = -1").first()
                    s = [float(r[f"s{i}"]) if r else 0.0 for i in range(self.width)]
                    model.nodes[1] = Node(1, 0, s[0], self.measure.prediction(s), max(0.0, self.measure.cost_of(s)), sums=tuple(s))
                if depth < max_depth and rows is not None:
                    found |= self.chosen(rows, min_rows)
                elif depth < max_depth:
                    found |= {r.node: r for r in self.best_splits(stats, min_rows).collect()}  # a row per open node
                if rows is None:
                    stats.unpersist()
                self.let_go()
            next_ = []
            for k in open_:
                node, r = model.nodes[k], found.get(k)
                if r is None or r.cost >= node.cost - min_gain * max(1.0, abs(node.cost)):
                    continue
                f = self.features[r.fid]
                node.feature, node.op = f.name, "in" if f.kind == "cat" else "<="
                node.threshold, node.categories = (None, sorted(r.categories)) if f.kind == "cat" else (r.val, None)
                left = r.left if self.bounded() else [float(r[f"l{i}"]) for i in range(self.width)]
                for child, s in ((2 * k, left), (2 * k + 1, [t - l for t, l in zip(node.sums, left)])):
                    model.nodes[child] = Node(child, depth + 1, s[0], self.measure.prediction(s), max(0.0, self.measure.cost_of(s)), k, sums=tuple(s))
                    next_.append(child)
            open_ = next_
            if not open_:
                break
        return model


LOOKUP, DEALT = 32 << 20, 8 << 20  # bytes of keys and bins up to which a branch, and the largest one, are sent to all tasks
SUMS = 64 << 20  # bytes of sums that a task holds


class Looked:
    """Statistics of a binned tree by look-ups, for branches of unique keys.

    Each relation becomes its keys and, for each feature, the number of the bin that its value is in; a branch below the root
    is one view of its edge key and the bins of all its relations.  A level reads the root's rows once, with their
    partners' bins looked up by key; a row's node and its place in each feature's sums follow from bins alone.  Small
    branches are sent to all tasks.  The largest one, if it has more than DEALT bytes, and the root are held in parts by its
    key, sorted, so that a level neither shuffles nor sorts them; others of more than LOOKUP bytes are joined by shuffles."""

    def __init__(self, grower: Grower):
        self.g, self.root = grower, grower.tree.root
        self.most = max(map(len, grower.bins.values()))  # the number of a feature's last bin: values above all edges
        self.kind = np.dtype("u1" if self.most < 1 << 8 else "<u2" if self.most < 1 << 16 else "<u4")
        self.held: list[DataFrame] = []
        self.order: list[int] = []  # features as their bins follow one another in a row

    def close(self) -> None:
        for df in self.held:
            df.unpersist()
        self.held = []

    def lot(self) -> int:
        """Nodes whose sums a task holds at once."""
        return max(1, min(LOT, SUMS // (8 * self.g.width * len(self.g.features) * (self.most + 1))))

    def own(self, name: str) -> list[int]:
        return [k for k, f in enumerate(self.g.features) if f.owner == name]

    def below(self, name: str) -> list[int]:
        return reduce(lambda a, c: a + self.below(c), self.g.tree.children[name], self.own(name))

    def packed(self, name: str) -> DataFrame:
        """A relation's keys, weight if it has one, label and bins."""
        df, own, kind = self.g.plain(name), [self.g.features[k] for k in self.own(name)], self.kind
        columns, edges = [f"f_{f.name}" for f in own], [np.array(self.g.bins[f.name]) for f in own]
        kept = [c for c in df.columns if c not in columns and (c != f"w_{name}" or self.g.spec.relations[name].mult)]
        if not own:
            return df.select(*[F.col(f"`{c}`") for c in kept])

        def run(batches):
            for b in batches:
                bins = np.empty((b.num_rows, len(columns)), kind)
                for j, (c, e) in enumerate(zip(columns, edges)):
                    bins[:, j] = np.searchsorted(e, b.column(c).to_numpy(zero_copy_only=False))
                yield pa.RecordBatch.from_arrays([*[b.column(c) for c in kept], as_binary(bins)], [*kept, f"b_{name}"])

        return df.mapInArrow(run, df.select(*[F.col(f"`{c}`") for c in kept]).schema.add(f"b_{name}", "binary"))

    def joined(self, name: str, df: DataFrame, views: dict[str, DataFrame], keys: list[str]) -> DataFrame:
        """df, a relation's rows, with the views of its branches: keys, weight and bins, under the relation's name."""
        for c, view in views.items():
            df = df.join(view, self.g.joined_on(name, c))
        names = [name, *self.g.tree.children[name]]
        weights, bins = [[f"{x}_{n}" for n in names if f"{x}_{n}" in df.columns] for x in "wb"]
        out = [F.col(f"`{k}`") for k in keys]
        if weights:
            out.append(reduce(lambda a, b: a * b, map(F.col, weights)).alias(f"w_{name}"))
        return df.select(*out, *([F.concat(*bins).alias(f"b_{name}")] if bins else []))

    def branch(self, name: str) -> DataFrame:
        """(edge key, weight, bins) of a relation and all below it."""
        views = {c: self.branch(c) for c in self.g.tree.children[name]}
        return self.joined(name, self.packed(name), views, [f"k_{name}_{c}" for _, c in self.g.tree.edge[name]])

    def bytes_of(self, name: str) -> int:
        """Bytes of a branch's view at most."""
        return self.g.spec.rows(name).count() * (8 * len(self.g.tree.edge[name]) + 12 + self.kind.itemsize * len(self.below(name)))

    @cached_property
    def rows(self) -> DataFrame:
        """The root's rows with all bins, w and y: a plan over held relations and views."""
        tree, root = self.g.tree, self.packed(self.root)
        size = {c: self.bytes_of(c) for c in tree.children[self.root]}
        views = {c: self.branch(c) for c in sorted(size, key=lambda c: (-size[c], c))}
        large = next((c for c in views if size[c] > DEALT), None)
        if large:
            parts = max(int(root.sparkSession.conf.get("spark.sql.shuffle.partitions")), self.g.spec.rows(self.root).count() >> 19)  # half a million rows a part

            def dealt(df: DataFrame, keys: list[str]) -> DataFrame:
                return df.repartition(parts, *keys).sortWithinPartitions(*keys)

            root = dealt(root, [f"k_{self.root}_{p}" for p, _ in tree.edge[large]])
            views[large] = dealt(views[large], [f"k_{large}_{c}" for _, c in tree.edge[large]])
        self.held = [root.persist(), *[v.persist() for v in views.values()]]
        hinted = {c: F.broadcast(v) if c != large and size[c] <= LOOKUP else v.hint("merge") for c, v in views.items()}
        self.order = self.below(self.root)
        return self.joined(self.root, root, hinted, ["y"])

    def statistics(self, model: TreeModel, nodes: list[int]) -> list[Row]:
        """Rows (node, fid, val, s0, s1, ...) as Grower.statistics has them, with one of fid -1 for each node."""
        g, rows = self.g, self.rows
        at = {k: j for j, k in enumerate(self.order)}
        place = {f.name: at[k] for k, f in enumerate(g.features)}
        tests = [(k, place[n.feature], bisect_left(g.bins[n.feature], n.threshold)) for k, n in sorted(model.nodes.items()) if n.feature]
        width, kind, measure, root, step = g.width, self.kind, g.measure, self.root, self.most + 1
        fids, slots, weighed = self.order, {n: j for j, n in enumerate(nodes)}, f"w_{self.root}" in rows.columns
        count = len(fids)

        def run(batches):
            total = np.zeros((width, count, len(nodes) * step))
            for b in batches:
                bins = from_binary(b.column(f"b_{root}"), count, kind).T
                y = b.column("y").to_numpy(zero_copy_only=False)
                w = b.column(f"w_{root}").fill_null(0.0).to_numpy(zero_copy_only=False) if weighed else np.ones(len(y))
                node = np.ones(len(y), np.int64)
                for k, j, least in tests:
                    here = np.flatnonzero(node == k)
                    node[here] = 2 * k + (bins[j, here] > least)
                slot = np.full(len(y), -1)
                for k, j in slots.items():
                    slot[node == k] = j
                open_ = np.flatnonzero(slot >= 0)
                if len(open_) < len(y):
                    bins, y, w, slot = bins[:, open_], y[open_], w[open_], slot[open_]
                base, sums = slot * step, measure.arrays(y, w)
                for j in range(count):
                    to = base + bins[j]
                    for i, s in enumerate(sums):
                        total[i, j] += np.bincount(to, s, total.shape[2])
            j, to = np.nonzero(total.any(0))
            fid, node = np.array(fids, np.int32)[j], np.array(nodes, np.int64)[to // step]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (node, fid, (to % step).astype(np.int32), *[t[j, to] for t in total])], ["node", "fid", "bin", *[f"s{i}" for i in range(width)]])

        schema = "node long, fid int, bin int, " + ", ".join(f"s{i} double" for i in range(width))
        got = rows.mapInArrow(run, schema).groupBy("node", "fid", "bin").agg(*[F.sum(f"s{i}").alias(f"s{i}") for i in range(width)]).collect()
        sums = lambda r: {f"s{i}": r[f"s{i}"] for i in range(width)}
        out = []
        for r in got:
            edges = g.bins[g.features[r.fid].name]
            out.append(Row(node=r.node, fid=r.fid, val=edges[r.bin] if r.bin < len(edges) else float("inf"), **sums(r)))
        for n in nodes:  # each feature's sums make up the node
            own = [r for r in out if r.node == n and r.fid == fids[0]]
            if own:
                out.append(Row(node=n, fid=-1, val=None, **{f"s{i}": sum(r[f"s{i}"] for r in own) for i in range(width)}))
        return out


KEPT, CHUNK = 1 << 13, 1 << 18  # values that stand for a chunk of rows, and its rows


def merged(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Sorted values with their numbers of rows, as KEPT of them at most: each stands for those between the one before and itself,
    so a rank moves by one in KEPT of the rows at most."""
    if not parts:
        return np.zeros(0), np.zeros(0, np.int64)
    values, at = np.unique(np.concatenate([v for v, _ in parts]), return_inverse=True)
    upto = np.cumsum(np.bincount(at, np.concatenate([c for _, c in parts]), len(values)).astype(np.int64))
    if len(values) > KEPT:
        kept = np.unique(np.searchsorted(upto, np.arange(1, KEPT + 1) * (upto[-1] / KEPT)).clip(max=len(values) - 1))
        values, upto = values[kept], upto[kept]
    return values, np.diff(upto, prepend=0)


def quantiles(df: DataFrame, parts: int) -> dict[str, list[float]]:
    """For each column the values, of those that occur, at which a part of 1, 2, ... in `parts` of its rows is reached; the last
    one is the greatest.  Up to KEPT distinct values they are exact, else ranks are off by three in KEPT of the rows at most."""
    names = df.columns

    def told(found: list[list]):
        for k, some in enumerate(found):
            v, c = merged(some)
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([v.tolist()], pa.list_(pa.float64())), pa.array([c.tolist()], pa.list_(pa.int64()))], ["k", "v", "c"])

    def sketched(batches):
        found, held, n = [[] for _ in names], [[] for _ in names], 0

        def close():
            for k, arrays in enumerate(held):
                v = np.concatenate(arrays)
                found[k].append(merged([(v, np.ones(len(v), np.int64))]))
                arrays.clear()

        for b in batches:
            for k, name in enumerate(names):
                held[k].append(b.column(name).drop_null().to_numpy(zero_copy_only=False))
            n += b.num_rows
            if n >= CHUNK:
                close()
                n = 0
        if n:
            close()
        yield from told(found)

    def together(batches):
        found = [[] for _ in names]
        for b in batches:
            for r in b.to_pylist():
                found[r["k"]].append((np.array(r["v"], float), np.array(r["c"], np.int64)))
        yield from told(found)

    schema, found = "k int, v array<double>, c array<long>", [[] for _ in names]
    for r in df.mapInArrow(sketched, schema).repartition(8).mapInArrow(together, schema).collect():
        found[r.k].append((np.array(r.v, float), np.array(r.c, np.int64)))
    out = {}
    for name, some in zip(names, found):
        values, rows = merged(some)
        upto = np.cumsum(rows)
        at = np.searchsorted(upto * parts, np.arange(1, parts + 1) * upto[-1]) if len(values) else []
        out[name] = [v for v in np.unique(values[at]).tolist() if v == v] if len(values) else []
    return out


def as_binary(rows: np.ndarray) -> pa.Array:
    """An array of bytes for each row."""
    n, width = len(rows), rows.shape[1] * rows.dtype.itemsize
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(np.arange(n + 1, dtype=np.int32) * np.int32(width)), pa.py_buffer(np.ascontiguousarray(rows))])


def from_binary(column: pa.Array, width: int, kind: np.dtype) -> np.ndarray:
    """Rows of `width` numbers from arrays of bytes."""
    column = column.cast(pa.binary())
    if not len(column):
        return np.zeros((0, width), kind)
    lo = np.frombuffer(column.buffers()[1], np.int32)[column.offset]
    return np.frombuffer(column.buffers()[2], np.uint8)[lo : lo + len(column) * width * kind.itemsize].view(kind).reshape(-1, width)


def as_column(c: Column | int) -> Column:
    return F.lit(c).cast("long") if isinstance(c, int) else c


def leaves(model: TreeModel) -> list[int]:
    return sorted(k for k, n in model.nodes.items() if n.feature is None)


def _grown(grower: Grower, max_depth: int, min_rows: int) -> TreeModel:
    try:
        return grower.grow(max_depth, min_rows)
    finally:
        grower.close()


def grow_regression_tree(spec: JoinSpec, features: list[Feature], label: Feature, max_depth: int = 4, min_rows: int = 1, max_bins: int | None = None) -> TreeModel:
    return _grown(Grower(spec, features, label, Measure("sse"), max_bins), max_depth, min_rows)


def grow_classification_tree(spec: JoinSpec, features: list[Feature], label: Feature, classes: int, cost: str = "gini", max_depth: int = 4, min_rows: int = 1, max_bins: int | None = None) -> TreeModel:
    """The label holds whole numbers from 0 to classes - 1."""
    return _grown(Grower(spec, features, label, Measure(cost, classes), max_bins), max_depth, min_rows)


def tree_size(model: TreeModel) -> int:
    return len(model.nodes)


def boosted_trees(spec: JoinSpec, features: list[Feature], label: Feature, rounds: int = 3, rate: float = 0.5, max_depth: int = 2, max_bins: int | None = 32) -> list[TreeModel]:
    """Each tree is grown on what the earlier ones leave.  A joined row's leaves in them follow from masks as its node does, so
    the joined rows are not stored in any round."""
    models: list[TreeModel] = []
    for _ in range(rounds):
        models.append(_grown(Grower(spec, features, label, Measure("sse"), max_bins, [(rate, m) for m in models]), max_depth, 1))
    return models


def boosted_column(models: list[TreeModel], rate: float = 0.5) -> Column:
    return reduce(lambda a, b: a + b, [F.lit(rate) * m.column() for m in models])


def random_forest(spec: JoinSpec, features: list[Feature], label: Feature, ids: list[str], trees: int = 3, max_depth: int = 3, max_bins: int | None = 32, per_tree: int | None = None) -> list[TreeModel]:
    """Rows of the root weigh 0 to 3 by a hash of ids and the tree's number, much as if drawn with replacement."""
    from dataclasses import replace

    out, root = [], spec.relations[label.owner]
    for t in range(trees):
        h = F.pmod(F.xxhash64(*ids, F.lit(t)), F.lit(1000))
        w = F.when(h < 368, 0).when(h < 736, 1).when(h < 920, 2).otherwise(3)
        rel = replace(root, df=root.df.withColumn("__bag", w).where("__bag > 0"), mult="__bag")
        some = [f for k, f in enumerate(features) if per_tree is None or (k + t) % len(features) < per_tree]
        out.append(grow_regression_tree(JoinSpec({**spec.relations, root.name: rel}, spec.on, spec.where, spec.null_policy), some, label, max_depth, max_bins=max_bins))
    return out
