"""Approximate nearest neighbours by cross-polytope hashing.

Three rounds of random signs and fast Hadamard transforms turn a vector; its bucket is the nearest signed axis.  A query probes the best buckets of each table, meets their vectors in blocks, and keeps its best by inner
product in double precision, worked out on the original vectors.  Vectors are indexed by direction within bands of nearly
equal length, and a query probes each band, so inner products of vectors of any length are served.

Equal vectors are one entry with their least ids, as many as an answer can hold, so a hot vector costs one entry.  Buckets
are counted first, and each is cut into as many salted blocks of bounded size as it needs, a dense cone of vectors too; blocks are taken in lots.  A query that finds fewer than k looks into all buckets of one table, which is exact.

Vectors that are null, zero, of another length than most, or hold null or non-finite numbers take no part.  Ties go to the
lesser id.  Ids are taken to be unique: a query leaves out all rows with its own id.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

BLOCK = 8192
LOT = 16  # buckets that one task call takes together, so that a query leaves it with one short list


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast transform of the rows, whose length is a power of two; kept orthonormal."""
    n, step = x.shape[1], 1
    while step < n:
        y = x.reshape(len(x), n // (2 * step), 2, step)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], 2).reshape(len(x), n)
        step *= 2
    return x / math.sqrt(n)


def rotations(dim: int, tables: int, hashes: int, seed: int) -> np.ndarray:
    """Signs (tables, hashes, 3, padded dim)."""
    return np.random.default_rng(seed).choice([-1.0, 1.0], (tables, hashes, 3, 1 << max(0, dim - 1).bit_length()))


def turned(x: np.ndarray, signs: np.ndarray) -> np.ndarray:
    """Both signs of each axis of the turned rows: 2 x padded dim values each, greatest at the nearest signed axis."""
    y = np.zeros((len(x), signs.shape[-1]))
    y[:, : x.shape[1]] = x
    for s in signs:
        y = hadamard(y * s)
    return np.concatenate([y, -y], 1)


def best_buckets(x: np.ndarray, signs: np.ndarray, probes: int) -> np.ndarray:
    """The best `probes` buckets of each row in one table, by the sum of the axis values of its hashes."""
    axes = 2 * signs.shape[-1]
    value, code = np.zeros((len(x), 1)), np.zeros((len(x), 1), np.int64)
    for s in signs:
        v = turned(x, s)
        top = np.argsort(-v, axis=1, kind="stable")[:, :probes]
        value = (value[:, :, None] + np.take_along_axis(v, top, 1)[:, None]).reshape(len(x), -1)
        code = (code[:, :, None] * axes + top[:, None]).reshape(len(x), -1)
        order = np.argsort(-value, axis=1, kind="stable")[:, :probes]
        value, code = np.take_along_axis(value, order, 1), np.take_along_axis(code, order, 1)
    return code


def matrix(column: pa.Array) -> np.ndarray:
    return np.array(column.flatten(), float).reshape(len(column), -1)


def usable_vectors(df: DataFrame, id_col: str, vec_col: str) -> tuple[DataFrame, int]:
    odd = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    kind = "array<float>" if df.schema[vec_col].dataType.simpleString() == "array<float>" else "array<double>"  # scores are in double
    rows = df.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast(kind).alias("v")).where(F.col("id").isNotNull() & F.col("v").isNotNull() & ~odd & F.exists("v", lambda x: x != 0))
    size = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    dim = size.d if size else 1
    return rows.where(F.size("v") == dim), dim


def nearest(df: DataFrame, is_query: Column, k: int = 20, tables: int = 6, probes: int = 24, id_col: str = "vec_id", vec_col: str = "embedding", seed: int = 11) -> DataFrame:
    """(query_id, rank, vec_id, score).  is_query: a condition on the column `id`."""
    rows, dim = usable_vectors(df, id_col, vec_col)
    order = Window.partitionBy("v").orderBy("id")
    members = common.settle(rows.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k + 1).withColumn("g", F.min("id").over(Window.partitionBy("v"))), "vectors")
    band = F.round(F.log2(F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x))) * 4).cast("int")
    entries = members.where("r = 1").select(F.col("id").alias("g"), "v", band.alias("band"))
    bands = sorted(r.band for r in entries.select("band").distinct().collect())  # a few per power of two
    total = rows.count()
    # one hash at every size, so that the share of a table that is probed does not fall as vectors come; growth is cut into blocks
    axes = 2 * (1 << max(0, dim - 1).bit_length())
    hashes = 1
    if probes >= axes:
        tables = 1  # all buckets of one table are everything
    queries = common.settle(rows.where(is_query).select(F.col("id").alias("q"), "v"), "queries")
    found = common.settle(_search(entries, queries, bands, rotations(dim, tables, hashes, seed), probes, k), "found")
    want = min(k, total - 1)
    best = _ranked(found, members, k)
    short = common.settle(queries.join(best.groupBy(F.col("query_id").alias("q")).count().where(F.col("count") >= want).select("q"), "q", "left_anti"), "short")
    if want > 0 and short.take(1):
        every = _search(entries, short, bands, rotations(dim, 1, 1, seed), axes, k)
        best = _ranked(found.unionByName(every), members, k)
    return best


def _ranked(found: DataFrame, members: DataFrame, k: int) -> DataFrame:
    each = found.dropDuplicates(["q", "g"]).join(members.select("g", F.col("id").alias("vec_id")), "g").where("vec_id <> q")
    order = Window.partitionBy("q").orderBy(F.desc("score"), "vec_id")
    return each.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select(F.col("q").alias("query_id"), "rank", "vec_id", "score")


def crowded(entries: DataFrame, signs: np.ndarray, block: int) -> dict[tuple[int, int, int], int]:
    """(table, band, bucket) -> number of blocks, of the buckets with more vectors than a block.  The driver gets a number for
    each bucket, whose number is bounded by tables, bands and axes."""

    def count(batches):
        for batch in batches:
            if batch.num_rows:
                x, band = matrix(batch.column("v")), np.array(batch.column("band")).astype(np.int64)
                for t in range(len(signs)):
                    at, n = np.unique(np.stack([band, best_buckets(x, signs[t], 1)[:, 0]]), axis=1, return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), t, np.int32)), pa.array(at[0]), pa.array(at[1]), pa.array(n)], ["t", "band", "b", "n"])

    seen = entries.select("band", "v").mapInArrow(count, "t int, band long, b long, n long").groupBy("t", "band", "b").agg(F.sum("n").alias("n")).where(F.col("n") > block)
    return {(r.t, r.band, r.b): -(-r.n // block) for r in seen.collect()}


def _search(entries: DataFrame, queries: DataFrame, bands: list[int], signs: np.ndarray, probes: int, k: int, block: int = BLOCK) -> DataFrame:
    """(q, g, score): the best k + 1 of each query in each block that it probes."""
    blocks = crowded(entries, signs, block)

    def salts(t: int, band, b: np.ndarray) -> np.ndarray:
        """Number of blocks of each bucket."""
        if not blocks:
            return np.ones(len(b), np.int64)
        return np.array([blocks.get((t, int(d), int(c)), 1) for d, c in zip(np.broadcast_to(band, len(b)), b)], np.int64)

    def index(batches):
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column("v"))
                g, band = np.array(batch.column("g")), np.array(batch.column("band"))
                for t in range(len(signs)):
                    b = best_buckets(x, signs[t], 1)[:, 0]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), t, np.int32)), batch.column("band"), pa.array(b), pa.array((g * 0x9E3779B1 >> 7) % salts(t, band, b)), batch.column("g"), batch.column("v")], ["t", "band", "b", "salt", "g", "v"])

    def probe(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                x, q = matrix(part.column("v")), np.array(part.column("q"))
                for t in range(len(signs)):
                    b = best_buckets(x, signs[t], probes)
                    n = b.shape[1]
                    for band in bands:
                        times = salts(t, band, b.ravel())
                        at = np.repeat(np.arange(b.size), times)
                        for lo in range(0, len(at), 8192):
                            some = at[lo : lo + 8192]
                            salt = np.arange(lo, lo + len(some)) - (np.cumsum(times) - times)[some]
                            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), t, np.int32)), pa.array(np.full(len(some), band, np.int32)), pa.array(b.ravel()[some]), pa.array(salt), pa.array(q[some // n]), part.column("v").take(pa.array(some // n))], ["t", "band", "b", "salt", "q", "v"])

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        out = [], [], []
        if left.num_rows and right.num_rows:
            left, right = left.sort_by("b"), right.sort_by("b")
            g, x, b = np.array(left.column("g")), matrix(left.column("v").combine_chunks()), np.array(left.column("b"))
            q, y, c = np.array(right.column("q")), matrix(right.column("v").combine_chunks()), np.array(right.column("b"))
            for bucket in np.unique(b):
                lo, hi = np.searchsorted(b, [bucket, bucket + 1])
                first, last = np.searchsorted(c, [bucket, bucket + 1])
                n = min(k + 1, hi - lo)
                for at in range(first, last, 512):
                    rows = slice(at, min(at + 512, last))
                    best = lo + np.argpartition(-(y[rows] @ x[lo:hi].T), n - 1, axis=1)[:, :n]
                    exact = (y[rows][:, None] * x[best]).sum(2)
                    for o, part in zip(out, (np.repeat(q[rows], n), g[best].ravel(), exact.ravel())):
                        o.append(part)
        kinds = np.int64, np.int64, float
        qs, gs, scores = (np.concatenate([np.zeros(0, kind), *o]) for o, kind in zip(out, kinds))
        order = np.lexsort((gs, -scores, qs))
        qs, gs, scores = qs[order], gs[order], scores[order]
        keep = np.arange(len(qs)) - np.searchsorted(qs, qs) <= k
        return pa.table({"q": qs[keep], "g": gs[keep], "score": scores[keep]})

    keys = ["t", "band", F.floor(F.col("b") / LOT), "salt"]
    kind = entries.schema["v"].dataType.simpleString()
    left = entries.mapInArrow(index, f"t int, band int, b long, salt long, g long, v {kind}")
    right = queries.mapInArrow(probe, f"t int, band int, b long, salt long, q long, v {kind}")
    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(meet, "q long, g long, score double")
