"""Learners beyond least squares and trees."""

from __future__ import annotations

import itertools
import math
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..moments import MomentMatrix, WIDE
from ..plans.views import aggregate, grouped_by_sets, monomials, naive_join, set_number
from ..spec import Feature, JoinSpec
from .linear import LinearModel


def pre_grouped(df: DataFrame, features: list[str], label: str, mult: str | None = None) -> DataFrame:
    """Distinct feature rows with their weight; persisted, since each round reads it."""
    w = F.sum(mult) if mult else F.count("*")
    return df.groupBy(*features, label).agg(w.cast("double").alias("__w")).persist()


def _scaled(df: DataFrame, features: list[str], label: str) -> tuple[DataFrame, np.ndarray, np.ndarray, float]:
    mean = [F.sum(F.col("__w") * F.col(f)) for f in features]
    r = df.agg(F.sum("__w"), *mean, *[F.sum(F.col("__w") * F.col(f) * F.col(f)) for f in features]).first()
    n, k = float(r[0]), len(features)
    m = np.array([float(v) for v in r[1 : k + 1]]) / n
    d = np.sqrt(np.maximum(np.array([float(v) for v in r[k + 1 :]]) / n - m * m, 1e-18))
    return df, m, np.where(d > 1e-8, d, np.inf), n


def _rounds(df: DataFrame, features: list[str], label: str, factor, max_iter: int, rate: float, l2: float, mult: str | None) -> LinearModel:
    """Gradient rounds whose residual depends on the parameters, so nothing can be hoisted: a scan of the grouped rows each."""
    rows, mean, dev, n = _scaled(pre_grouped(df, features, label, mult), features, label)
    z = [(F.col(f) - F.lit(float(m))) / F.lit(float(d)) for f, m, d in zip(features, mean, dev)]
    w, trace = np.zeros(len(features) + 1), []
    for k in range(max_iter):
        score = reduce(lambda a, b: a + b, [F.lit(float(t)) * c for t, c in zip(w[1:], z)], F.lit(float(w[0])))
        r = factor(score, F.col(label)) * F.col("__w")
        g = np.array([float(v) for v in rows.withColumn("__r", r).agg(F.sum("__r"), *[F.sum(F.col("__r") * c) for c in z]).first()]) / n
        g[1:] += l2 * w[1:]
        trace.append((k, float("nan"), float(np.linalg.norm(g))))
        w = w - rate / math.sqrt(1 + k / 10) * g
    rows.unpersist()
    b = w[1:] / dev
    return LinearModel(["1", *features], np.append(w[0] - b @ mean, b), trace)


def logistic(df: DataFrame, features: list[str], label: str, max_iter: int = 30, rate: float = 2.0, l2: float = 1e-4, mult: str | None = None) -> LinearModel:
    """label 0 or 1."""
    return _rounds(df, features, label, lambda s, y: 1 / (1 + F.exp(-s)) - y, max_iter, rate, l2, mult)


def linear_svm(df: DataFrame, features: list[str], label: str, max_iter: int = 30, rate: float = 1.0, l2: float = 1e-3, mult: str | None = None) -> LinearModel:
    """label 0 or 1; sub-gradient of the hinge loss."""
    sign = lambda y: 2 * y - 1
    return _rounds(df, features, label, lambda s, y: F.when(sign(y) * s < 1, -sign(y)).otherwise(F.lit(0.0)), max_iter, rate, l2, mult)


def pca(m: MomentMatrix, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(variances, components as rows); the entry of largest size of each component is positive."""
    v = m.floats()
    n, mean = v[0, 0], v[0, 1:] / v[0, 0]
    values, vectors = np.linalg.eigh(v[1:, 1:] / n - np.outer(mean, mean))
    values, vectors = values[::-1][:k], vectors[:, ::-1][:, :k].T
    sign = np.sign(vectors[np.arange(len(vectors)), np.abs(vectors).argmax(1)])
    return values, vectors * sign[:, None]


def lloyd_sums(df: DataFrame, vec: str, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(sums, counts) of the vectors nearest to each centre; a block of k x d numbers per task."""
    k, d = centres.shape

    def run(batches):
        s, c = np.zeros((k, d)), np.zeros(k)
        for b in batches:
            if b.num_rows:
                x = np.array(b.column("v").flatten(), float).reshape(b.num_rows, -1)
                at = ((x * x).sum(1)[:, None] - 2 * x @ centres.T + (centres * centres).sum(1)).argmin(1)
                np.add.at(s, at, x)
                c += np.bincount(at, minlength=k)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(k)), pa.array(c), pa.array(s.tolist(), pa.list_(pa.float64()))], ["c", "n", "s"])

    rows = df.select(F.col(vec).cast("array<double>").alias("v")).mapInArrow(run, "c long, n double, s array<double>")
    flat = rows.select("c", "n", F.posexplode("s").alias("j", "v")).groupBy("c", "j").agg(F.sum("v").alias("v"), F.sum("n").alias("n")).collect()
    sums, counts = np.zeros((k, d)), np.zeros(k)
    for r in flat:
        sums[r.c, r.j], counts[r.c] = r.v, r.n
    return sums, counts


def kmeans(df: DataFrame, vec: str, id_col: str, k: int, max_iter: int = 10, tol: float = 1e-6) -> np.ndarray:
    """Starts at the k rows of least id; a centre that loses all its rows stays."""
    first = df.orderBy(id_col).limit(k).select(vec).collect()
    centres = np.array([list(r[0]) for r in first], float)
    for _ in range(max_iter):
        sums, counts = lloyd_sums(df, vec, centres)
        new = np.where(counts[:, None] > 0, sums / np.maximum(counts, 1)[:, None], centres)
        moved = np.abs(new - centres).max()
        centres = new
        if moved < tol:
            break
    return centres


def mutual_information(spec: JoinSpec, cats: list[Feature]) -> list[tuple[str, str, float]]:
    """(a, b, mutual information) of all pairs of categorical features, in nats.

    One grouping-sets pass over the joined rows' categories counts all values and pairs.  Each set's counts are summed to
    its entropy, and information is H(a) + H(b) - H(a, b), so no counts meet in a join and the driver gets one row a set.
    A null category is a value of its own; without rows all are 0."""
    names = [c.name for c in cats]
    pairs = list(itertools.combinations(names, 2))
    if not pairs:
        return []
    counts = grouped_by_sets(naive_join(spec, cats), names, [*((n,) for n in names), *pairs], [F.sum("__mult").alias("__n")]).where("__n > 0")
    sums = counts.groupBy("__g").agg(F.sum("__n"), F.sum(F.col("__n") * F.log("__n"))).collect()
    entropy = {g: math.log(n) - s / n for g, n, s in sums}
    h = lambda *s: entropy.get(set_number(names, s), 0.0)
    return [(a, b, max(0.0, h(a) + h(b) - h(a, b))) for a, b in pairs]


def chow_liu(spec: JoinSpec, cats: list[Feature]) -> list[tuple[str, str, float]]:
    """Edges (a, b, mutual information) of the maximum spanning tree over categorical features; ties go by name."""
    info = mutual_information(spec, cats)
    up = {c.name: c.name for c in cats}

    def top(n):
        while up[n] != n:
            n = up[n]
        return n

    out = []
    for a, b, mi in sorted(info, key=lambda x: (-round(x[2], 12), x[0], x[1])):
        if top(a) != top(b):
            up[top(a)] = top(b)
            out.append((a, b, mi))
    return out


def factorisation_machine(spec: JoinSpec, features: list[Feature], label: Feature, rank: int = 2, max_iter: int = 30, l2: float = 1e-3, seed: int = 3) -> dict:
    """Degree 2, by alternating least squares on moments of degree 4, summed once: each factor's problem is linear when the
    others stand still.  Returns w0, w, V for standardised features, with the mean squared error by round."""
    names = [f.name for f in features]
    batch = sorted(set(monomials(names, 4)) | {tuple(sorted((*m, label.name))) for m in monomials(names, 2)} | {(label.name, label.name)}, key=lambda m: (len(m), m))
    centre = aggregate(spec, [*features, label], [(), *((n,) for n in names), *((n, n) for n in names)]).first()
    n, k = float(centre[0]), len(names)
    mean = np.array(centre[1 : k + 1], float) / n
    dev = np.sqrt(np.maximum(np.array(centre[k + 1 :], float) / n - mean**2, 1e-18))
    from dataclasses import replace

    scaled = [replace(f, expr=f"(({f.expr}) - {m!r}) / {d!r}") for f, m, d in zip(features, mean.tolist(), dev.tolist())]
    sums: dict = {}
    for lo in range(0, len(batch), WIDE):
        part = batch[lo : lo + WIDE]
        sums |= dict(zip(part, [float(v) / n for v in aggregate(spec, [*scaled, label], part).first()]))
    pairs = list(itertools.combinations(range(k), 2))
    phi = [(), *((x,) for x in names), *(tuple(sorted((names[i], names[j]))) for i, j in pairs)]
    G = np.array([[sums[tuple(sorted((*a, *b)))] for b in phi] for a in phi])
    b = np.array([sums[tuple(sorted((*a, label.name)))] for a in phi])
    yy = sums[(label.name, label.name)]
    rng = np.random.default_rng(seed)
    V, w, trace = rng.normal(0, 0.1, (k, rank)), np.zeros(k + 1), []

    def full():
        return np.concatenate([w, [V[i] @ V[j] for i, j in pairs]])

    for _ in range(max_iter):
        L = k + 1
        w = np.linalg.solve(G[:L, :L] + l2 * np.eye(L), b[:L] - G[:L, L:] @ full()[L:])
        for i in range(k):
            A = np.zeros((len(phi), rank))  # the parameters as a linear function of V[i]
            rest = full()
            for t, (p, q) in enumerate(pairs):
                if i in (p, q):
                    A[L + t] = V[q if p == i else p]
                    rest[L + t] = 0
            V[i] = np.linalg.solve(A.T @ G @ A + l2 * np.eye(rank), A.T @ (b - G @ rest))
        t = full()
        trace.append(float(t @ G @ t - 2 * t @ b + yy))
    return {"w": w, "V": V, "mse": trace, "linear_mse": float(yy - b[: k + 1] @ np.linalg.lstsq(G[: k + 1, : k + 1], b[: k + 1], rcond=None)[0])}
