"""Linear regression from moments: gradient descent, closed form, ridge, coordinate descent, subset search."""

from __future__ import annotations

import itertools
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..moments import MomentMatrix
from ..plans.views import naive_join
from ..spec import Feature, JoinSpec


@dataclass
class LinearModel:
    names: list[str]
    theta: np.ndarray
    trace: list[tuple] = field(default_factory=list)

    def column(self) -> Column:
        return reduce(lambda a, b: a + b, [F.lit(float(t)) if n == "1" else F.lit(float(t)) * F.col(n) for n, t in zip(self.names, self.theta)])

    def predict(self, df: DataFrame, out: str = "prediction") -> DataFrame:
        return df.withColumn(out, self.column())

    def to_df(self, spark: SparkSession, digits: int | None = None) -> DataFrame:
        return spark.createDataFrame([(n, round(float(t), digits) + 0.0 if digits is not None else float(t)) for n, t in zip(self.names, self.theta)], "feature string, theta double")

    def save(self, spark: SparkSession, path: str) -> None:
        self.to_df(spark).coalesce(1).write.mode("overwrite").parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> "LinearModel":
        rows = spark.read.parquet(path).collect()
        return LinearModel([r.feature for r in rows], np.array([r.theta for r in rows]))


def _split(m: MomentMatrix) -> tuple[np.ndarray, np.ndarray, float, float]:
    """X'X, X'y, y'y and the number of rows; the label is the last name."""
    v = m.floats()
    return v[:-1, :-1], v[:-1, -1], v[-1, -1], v[0, 0]


def _back(m: MomentMatrix, w: np.ndarray, mean: np.ndarray, dev: np.ndarray) -> np.ndarray:
    """Weights of standardised features to weights of the given ones, the intercept first."""
    safe = np.where(dev[:-1] > 1e-12 * np.maximum(1, np.abs(mean[:-1])), dev[:-1], np.inf)
    b = w * dev[-1] / safe
    return np.append(mean[-1] - b @ mean[:-1], b)


def loss(m: MomentMatrix, theta: np.ndarray) -> float:
    """Half the mean squared residual, from moments alone."""
    xx, xy, yy, n = _split(m)
    return float((theta @ xx @ theta - 2 * theta @ xy + yy) / (2 * n))


def loss_scan(df: DataFrame, model: LinearModel, label: str, mult: str = "__mult") -> float:
    r = df.agg(F.sum(F.col(mult) * (model.column() - F.col(label)) ** 2).alias("s"), F.sum(mult).alias("n")).first()
    return float(r.s) / (2 * float(r.n))


def bgd(m: MomentMatrix, alpha: float | None = None, max_iter: int = 50, tol: float | None = None, l2: float = 0.0, raw: bool = False, theta0: np.ndarray | None = None) -> LinearModel:
    """Batch gradient descent on the hoisted moments: no round touches data.  Steps are taken on standardised features
    unless raw; the step factor defaults to the reciprocal of the largest curvature."""
    names, trace = m.names[:-1], []
    if raw:
        xx, xy, yy, n = _split(m)
        a, b = xx / n, xy / n
    else:
        c, mean, dev = m.standardise()
        a, b = c[:-1, :-1], c[:-1, -1]
    a = a + l2 * np.eye(len(a))
    alpha = alpha if alpha is not None else 1 / max(float(np.linalg.eigvalsh(a)[-1]) if len(a) else 1, 1e-12)
    w = np.zeros(len(a)) if theta0 is None else np.array(theta0, float)
    for k in range(max_iter):
        g = a @ w - b
        trace.append((k, float(w @ a @ w / 2 - w @ b), float(np.linalg.norm(g))))
        if tol is not None and trace[-1][2] < tol:
            break
        w = w - alpha * g
    return LinearModel(names, w if raw else _back(m, w, mean, dev), trace)


def bgd_naive(spec: JoinSpec, features: list[Feature], label: Feature, stats: MomentMatrix | None = None, max_iter: int = 50, alpha: float | None = None, joined: DataFrame | None = None, raw: bool = False) -> LinearModel:
    """The unoptimised program: each round sums residuals over the joined rows.  Not raw, stats gives the scaling and step."""
    df = (joined if joined is not None else naive_join(spec, [*features, label])).persist()
    names = [f.name for f in features]
    if raw:
        names, y, n = ["1", *names], F.col(label.name), float(df.agg(F.sum("__mult")).first()[0])
        z = {x: F.lit(1.0) if x == "1" else F.col(x) for x in names}
    else:
        c, mean, dev = stats.standardise()
        alpha = alpha if alpha is not None else 1 / float(np.linalg.eigvalsh(c[:-1, :-1])[-1])
        z = {x: (F.col(x) - float(mean[i])) / (float(dev[i]) if dev[i] > 0 else float("inf")) for i, x in enumerate(names)}
        y, n = (F.col(label.name) - float(mean[-1])) / float(dev[-1]), float(stats.count)
    w, trace = np.zeros(len(names)), []
    for k in range(max_iter):
        residual = reduce(lambda a, b: a + b, [F.lit(float(t)) * z[x] for x, t in zip(names, w)]) - y
        g = np.array([float(v) for v in df.withColumn("__r", residual * F.col("__mult")).agg(*[F.sum(F.col("__r") * z[x]) for x in names]).first()]) / n
        trace.append((k, float("nan"), float(np.linalg.norm(g))))
        w = w - alpha * g
    df.unpersist()
    return LinearModel(names, w, trace) if raw else LinearModel(["1", *names], _back(stats, w, mean, dev), trace)


def solve_normal(m: MomentMatrix, l2: float = 0.0) -> LinearModel:
    """Closed form on standardised moments; least squares where rank is short."""
    c, mean, dev = m.standardise()
    a, b = c[:-1, :-1] + l2 * np.eye(len(c) - 1), c[:-1, -1]
    w = np.linalg.lstsq(a, b, rcond=1e-11)[0]
    return LinearModel(m.names[:-1], _back(m, w, mean, dev))


def ridge(m: MomentMatrix, l2: float) -> LinearModel:
    return solve_normal(m, l2)


def coordinate_descent(m: MomentMatrix, l1: float = 0.0, l2: float = 0.0, max_iter: int = 500, tol: float = 1e-10) -> LinearModel:
    """Elastic net on standardised moments."""
    c, mean, dev = m.standardise()
    a, b = c[:-1, :-1], c[:-1, -1]
    w = np.zeros(len(a))
    for _ in range(max_iter):
        old = w.copy()
        for j in range(len(w)):
            r = b[j] - a[j] @ w + a[j, j] * w[j]
            w[j] = np.sign(r) * max(abs(r) - l1, 0) / (a[j, j] + l2) if a[j, j] + l2 > 0 else 0.0
        if np.abs(w - old).max(initial=0) < tol:
            break
    return LinearModel(m.names[:-1], _back(m, w, mean, dev))


def rss(m: MomentMatrix, model: LinearModel) -> float:
    return 2 * float(m.floats()[0, 0]) * loss(m, model.theta)


def select_features(m: MomentMatrix, k: int, how: str = "forward") -> list[tuple[int, str, float]]:
    """(size, features, residual sum of squares) of the best subsets, all from one matrix: no further scan."""
    label, names = m.names[-1], m.names[1:-1]

    def cost(s) -> float:
        sub = m.select(["1", *s, label])
        return rss(sub, solve_normal(sub))

    out = []
    if how == "all":
        for size in range(1, k + 1):
            best = min(itertools.combinations(names, size), key=lambda s: (round(cost(s), 6), s))
            out.append((size, ",".join(best), cost(best)))
        return out
    chosen: list[str] = [] if how == "forward" else list(names)
    while len(chosen) < k if how == "forward" else len(chosen) > k:
        if how == "forward":
            chosen = min(([*chosen, n] for n in names if n not in chosen), key=lambda s: (round(cost(s), 6), s))
        else:
            chosen = min(([c for c in chosen if c != n] for n in chosen), key=lambda s: (round(cost(s), 6), s))
        out.append((len(chosen), ",".join(chosen), cost(chosen)))
    return out


def rmse(df: DataFrame, label: str, prediction: str = "prediction", mult: str | None = None) -> float:
    w = F.col(mult) if mult else F.lit(1.0)
    return float(df.agg(F.sqrt(F.sum(w * (F.col(prediction) - F.col(label)) ** 2) / F.sum(w))).first()[0])


@dataclass
class Scale:
    """Means and deviations of joined rows by themselves, the label last: what SGD needs of a moment matrix."""

    count: float
    mean: np.ndarray
    dev: np.ndarray

    def standardise(self) -> tuple[None, np.ndarray, np.ndarray]:
        return None, self.mean, self.dev

    @staticmethod
    def of(df: DataFrame, columns: list[str]) -> "Scale":
        r = list(df.agg(F.count("*"), *[F.avg(c) for c in columns], *[F.stddev_pop(c) for c in columns]).first())
        n = len(columns)
        return Scale(float(r[0]), np.array([float(v or 0) for v in r[1 : n + 1]]), np.array([float(v or 0) for v in r[n + 1 :]]))


#: Bytes of blocks that the driver of SGD takes at a time.
TURN_BYTES = 16 << 20


def sgd(df: DataFrame, features: list[str], label: str, stats: MomentMatrix | Scale, batch_size: int = 100_000, epochs: int = 1, rate: float = 0.1) -> LinearModel:
    """Mini-batches of rows as they are read; a batch's gradient is the mean over its rows, and batches take their turn in
    order of partitions.  A task holds one batch's block of sums at a time, all blocks of an epoch come from one job, and
    the driver takes them by partitions, as many at a time as TURN_BYTES hold, and one at least."""
    import pyarrow as pa

    n = len(features) + 2
    _, mean, dev = stats.standardise()
    dev = np.where(dev > 0, dev, np.inf)

    def run(batches):
        total, held = np.zeros((n, n)), 0

        def block():
            return pa.RecordBatch.from_arrays([pa.array([total.ravel().tolist()], pa.list_(pa.float64()))], ["s"])

        for b in batches:
            x = np.empty((n, b.num_rows))
            x[0] = 1
            for i, f in enumerate([*features, label]):
                np.subtract(np.asarray(b.column(f), float), mean[i], out=x[i + 1])
                x[i + 1] /= dev[i]
            while x.shape[1]:
                part, x = x[:, : batch_size - held], x[:, batch_size - held :]
                total, held = total + part @ part.T, held + part.shape[1]
                if held == batch_size:
                    yield block()
                    total, held = np.zeros((n, n)), 0
        if held:
            yield block()

    blocks = df.select(*[F.col(f).cast("double").alias(f) for f in [*features, label]]).mapInArrow(run, "s array<double>").persist()
    w = np.zeros(n - 1)
    try:
        placed = blocks.select(F.monotonically_increasing_id().alias("at"), "s").withColumn("part", F.shiftright("at", 33))
        turns: list[list[int]] = []  # first and last partition, number of blocks
        for r in sorted(placed.groupBy("part").agg(F.count("*").alias("n")).collect(), key=lambda r: r.part):
            if turns and (turns[-1][2] + r.n) * n * n * 8 <= TURN_BYTES:
                turns[-1][1:] = r.part, turns[-1][2] + r.n
            else:
                turns.append([r.part, r.part, r.n])
        for _ in range(epochs):
            for first, last, _ in turns:
                for r in sorted(placed.where(F.col("part").between(first, last)).collect(), key=lambda r: r["at"]):
                    s = np.array(r.s).reshape(n, n)
                    w = w - rate * (s[:-1, :-1] @ w - s[:-1, -1]) / s[0, 0]
    finally:
        blocks.unpersist()
    theta = _back(stats, w[1:], mean, np.where(np.isinf(dev), 0, dev))
    theta[0] += w[0] * (dev[-1] if np.isfinite(dev[-1]) else 0)
    return LinearModel(["1", *features], theta)
