"""The non-centred second-moment matrix of the joined rows, and its algebra."""

from __future__ import annotations

import itertools
import json
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .plans.views import aggregate, grouped_by_sets, monomials, naive_join, set_number
from .spec import Feature, JoinSpec

#: Beyond this many sums generated code gives way; then chunks (exact) or Arrow blocks (floating) take over.
WIDE = 90


@dataclass
class MomentMatrix:
    """names starts with "1"; values[i, j] = sum of names[i] * names[j] over the joined rows.  Exact matrices hold Python
    integers, scaled by 10 ** scale of each feature."""

    names: list[str]
    values: np.ndarray
    scales: dict[str, int]
    exact: bool = False

    @property
    def count(self):
        return self.values[0, 0]

    def at(self, a: str, b: str):
        return self.values[self.names.index(a), self.names.index(b)]

    def floats(self) -> np.ndarray:
        out = np.array([[float(v) for v in row] for row in self.values])
        s = np.array([10.0 ** -self.scales.get(n, 0) for n in self.names])
        return out * np.outer(s, s)

    def __add__(self, o: "MomentMatrix") -> "MomentMatrix":
        return MomentMatrix(self.names, self.values + o.select(self.names).values, self.scales, self.exact)

    def __sub__(self, o: "MomentMatrix") -> "MomentMatrix":
        return MomentMatrix(self.names, self.values - o.select(self.names).values, self.scales, self.exact)

    def select(self, names: list[str]) -> "MomentMatrix":
        at = [self.names.index(n) for n in names]
        return MomentMatrix(list(names), self.values[np.ix_(at, at)], self.scales, self.exact)

    def standardise(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(correlation-like matrix of all but the intercept, means, deviations).  Exact matrices are centred in whole
        numbers, n * sum(xy) - sum(x) * sum(y), so no digits cancel."""
        n = self.values[0, 0]
        c = np.array([[float(n * self.values[i, j] - self.values[0, i] * self.values[0, j]) for j in range(1, len(self.names))] for i in range(1, len(self.names))])
        s = np.array([10.0 ** -self.scales.get(k, 0) for k in self.names[1:]])
        n = float(n)
        c = c * np.outer(s, s) / max(n * n, 1.0)
        mean = np.array([float(v) for v in self.values[0, 1:]]) * s / max(n, 1.0)
        dev = np.sqrt(np.maximum(np.diag(c), 0))
        safe = np.where(dev > 1e-12 * np.maximum(1, np.abs(mean)), dev, np.inf)  # constant features carry nothing
        return c / np.outer(safe, safe), mean, dev

    def rows(self) -> list[tuple]:
        return [(self.names[i], self.names[j], self.values[i, j]) for i in range(len(self.names)) for j in range(i, len(self.names))]

    def to_df(self, spark: SparkSession) -> DataFrame:
        """(f1, f2, value) of the upper triangle; value as text if exact."""
        kind = "string" if self.exact else "double"
        return spark.createDataFrame([(a, b, str(v) if self.exact else float(v)) for a, b, v in self.rows()], f"f1 string, f2 string, value {kind}")

    def save(self, spark: SparkSession, path: str) -> None:
        meta = json.dumps({"names": self.names, "scales": self.scales, "exact": self.exact, "values": [[str(v) for v in r] for r in self.values]})
        spark.createDataFrame([(meta,)], "matrix string").coalesce(1).write.mode("overwrite").parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> "MomentMatrix":
        m = json.loads(spark.read.parquet(path).first().matrix)
        kind = int if m["exact"] else float
        return MomentMatrix(m["names"], np.array([[kind(v) for v in r] for r in m["values"]], dtype=object if m["exact"] else float), m["scales"], m["exact"])


def moment_matrix(spec: JoinSpec, features: list[Feature], label: Feature | None = None, strategy: str = "auto", exact: bool = False, root: str | None = None) -> MomentMatrix:
    """One job over the base relations.  auto: views in one pass for floating sums of a narrow batch, else Arrow blocks, whose
    exact sums are of whole numbers in limbs and not of decimals."""
    every = [f for f in features if f.name != "1"] + ([label] if label else [])
    spec.check(every)
    names = ["1", *(f.name for f in every)]
    batch = monomials(names)
    if strategy == "auto":
        strategy = "multi" if len(batch) <= WIDE and not exact else "gram"
    if strategy == "gram" and exact:
        return MomentMatrix(names, gram_exact(naive_join(spec, every, exact=True), names[1:]), {f.name: f.scale for f in every}, True)
    if strategy == "gram":
        return MomentMatrix(names, gram(naive_join(spec, every), names[1:]), {})
    if strategy == "chunked":
        sums = [v for lo in range(0, len(batch), WIDE) for v in aggregate(spec, every, batch[lo : lo + WIDE], "multi", exact, root=root).first()]
    else:
        sums = list(aggregate(spec, every, batch, strategy, exact, root=root).first())
    return from_sums(names, batch, sums, {f.name: f.scale for f in every} if exact else {}, exact)


def from_sums(names: list[str], batch: list, sums: list, scales: dict, exact: bool) -> MomentMatrix:
    got = {m: (int(v or 0) if exact else float(v or 0)) for m, v in zip(batch, sums)}
    n = len(names)
    values = np.empty((n, n), dtype=object if exact else float)
    for i in range(n):
        for j in range(n):
            values[i, j] = got[tuple(sorted(x for x in (names[i], names[j]) if x != "1"))]
    return MomentMatrix(names, values, scales, exact)


def gram(df: DataFrame, columns: list[str], mult: str = "__mult") -> np.ndarray:
    """X'X with an intercept: a block per task; the blocks are summed by place, in no fixed order."""
    n = len(columns) + 1

    def run(batches):
        total = np.zeros((n, n))
        for batch in batches:
            x, weight = np.empty((n, batch.num_rows)), np.asarray(batch.column(mult), float)
            x[0] = 1
            for i, c in enumerate(columns):
                x[i + 1] = np.asarray(batch.column(c), float)
            total += (x if (weight == 1).all() else x * weight) @ x.T
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(n), n)), pa.array(np.tile(np.arange(n), n)), pa.array(total.ravel())], ["i", "j", "v"])

    rows = df.select(*[F.col(c).cast("double").alias(c) for c in columns], F.col(mult).cast("double").alias(mult)).mapInArrow(run, "i long, j long, v double")
    out = np.zeros((n, n))
    for r in rows.groupBy("i", "j").agg(F.sum("v").alias("v")).collect():
        out[r.i, r.j] = r.v
    return (out + out.T) / 2


LIMB = 21  # bits; products of limbs over 2048 rows stay below 2^53, where floating sums are exact
BLOCK = 1 << 11


def limbs(x: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """Columns of whole numbers as columns of limbs (the last one signed) with (column, shift); only limbs that are in use."""
    out, place = [], []
    for k in range(x.shape[1]):
        c, most = x[:, k], int(np.abs(x[:, k]).max(initial=0))
        for part in range(3):
            last = most < 1 << (LIMB * (part + 1) - 1)
            out.append(c if last or part == 2 else c & ((1 << LIMB) - 1))
            place.append((k, LIMB * part))
            if last:
                break
            c = c >> LIMB
    return np.stack(out, 1).astype(float), place


def exact_block(x: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """X' diag(weight) X of 64-bit whole numbers as Python integers."""
    n = x.shape[1]
    total = np.zeros((n, n), object)
    if (weight == 1).all():
        parts, place = limbs(x)
        low = np.zeros((len(place), len(place)), np.int64)
        high = np.zeros_like(low)
        for lo in range(0, len(x), BLOCK):
            b = parts[lo : lo + BLOCK]
            got = (b.T @ b).astype(np.int64)
            low += got & 0xFFFFFFFF
            high += got >> 32
        for i, (a, s) in enumerate(place):
            for j, (b, t) in enumerate(place):
                total[a, b] += (int(high[i, j]) << 32) + int(low[i, j]) << s + t
        return total
    rows = x.astype(object)
    return (rows * weight.astype(object)[:, None]).T @ rows


def gram_exact(df: DataFrame, columns: list[str], mult: str = "__mult") -> np.ndarray:
    """X'X with an intercept of whole numbers of at most 18 digits: a block per task, summed as decimals."""
    n = len(columns) + 1
    upper = [(i, j) for i in range(n) for j in range(i, n)]

    def run(batches):
        total = np.zeros((n, n), object)
        for batch in batches:
            x = np.column_stack([np.ones(batch.num_rows, np.int64), *[np.asarray(batch.column(c), np.int64) for c in columns]])
            total = total + exact_block(x, np.asarray(batch.column(mult), np.int64))
        yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in upper]), pa.array([j for _, j in upper]), pa.array([str(total[i, j]) for i, j in upper])], ["i", "j", "v"])

    rows = df.select(*[F.col(c).cast("long").alias(c) for c in columns], F.col(mult).cast("long").alias(mult)).mapInArrow(run, "i long, j long, v string")
    out = np.zeros((n, n), object)
    for r in rows.groupBy("i", "j").agg(F.sum(F.col("v").cast("decimal(38,0)")).alias("v")).collect():
        out[r.i, r.j] = out[r.j, r.i] = int(r.v)
    return out


def moment_tensor(spec: JoinSpec, cont: list[Feature], cats: list[Feature]) -> DataFrame:
    """Sparse one-hot moments (f1, c1, f2, c2, value): only pairs that occur.  Two passes at any number of categories, each
    combined before its shuffle: single categories with their continuous partners, and pairs of categories with counts."""
    names = [c.name for c in cats]
    singles, pairs = [(n,) for n in names], list(itertools.combinations(names, 2))

    def own(sets: list, value) -> Column:
        """What `value` makes of the categories that a row is grouped by."""
        return F.coalesce(*[F.when(F.col("__g") == set_number(names, s), value(s)) for s in sets])

    sums = {"": F.sum("__mult")} | {c.name: F.sum(F.col("__mult") * F.col(c.name)) for c in cont}
    got = grouped_by_sets(naive_join(spec, [*cont, *cats]), names, singles, [v.alias(f"__a{i}") for i, v in enumerate(sums.values())])
    f, c = own(singles, lambda s: F.lit(s[0])), own(singles, lambda s: F.col(s[0]))
    same = [F.struct(f.alias("f1"), c.alias("c1"), (F.lit(n) if n else f).alias("f2"), (F.lit("") if n else c).alias("c2"), F.col(f"__a{i}").alias("value")) for i, n in enumerate(sums)]
    out = got.select(F.explode(F.array(*same)).alias("r")).select("r.*")
    if pairs:
        both = grouped_by_sets(naive_join(spec, cats), names, pairs, [F.sum("__mult").alias("__a0")])
        columns = {f"{kind}{k + 1}": own(pairs, lambda s: value(s[k])) for k in (0, 1) for kind, value in (("f", F.lit), ("c", F.col))}
        out = out.unionByName(both.select(*[v.alias(k) for k, v in columns.items()], F.col("__a0").alias("value")))
    return out
