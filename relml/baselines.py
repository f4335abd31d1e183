"""What the paper compares with: materialise the joined rows, then learn from them with a library."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import datasets as ds
from .catalog import query, sig, sig_sql
from .learn import linear
from .plans.views import naive_join
from .spec import Feature, JoinSpec


class MemoryBudgetExceeded(MemoryError):
    """The driver would hold more than it may."""


def materialise_pandas(spec: JoinSpec, features: list[Feature], limit_rows: int = 200_000):
    """The joined rows in the driver's memory, behind a guard."""
    df = naive_join(spec, features)
    if (n := df.count()) > limit_rows:
        raise MemoryBudgetExceeded(f"{n} rows, limit {limit_rows}")
    return df.toPandas()


def assembled(df: DataFrame, features: list[str]) -> DataFrame:
    from pyspark.ml.feature import VectorAssembler

    return VectorAssembler(inputCols=features, outputCol="features").transform(df)


def library_linear(spec: JoinSpec, features: list[Feature], label: Feature) -> linear.LinearModel:
    from pyspark.ml.regression import LinearRegression

    names = [f.name for f in features]
    joined = naive_join(spec, [*features, label]).persist()
    try:
        m = LinearRegression(labelCol=label.name, solver="normal", regParam=0.0).fit(assembled(joined, names))
    finally:
        joined.unpersist()
    return linear.LinearModel(["1", *names], np.append(m.intercept, m.coefficients.toArray()))


def held_rows(spec: JoinSpec, features: list[Feature]) -> DataFrame:
    """The joined rows, held; whole numbers stay such, as the cache makes them small."""
    kinds = {f.name: spec.relations[f.owner].df.select(F.expr(f.expr).alias("x")).schema["x"].dataType.typeName() for f in features}
    return naive_join(spec, features).select(*[F.col(n).cast(k) if k in ("byte", "short", "integer") else F.col(n) for n, k in kinds.items()], "__mult").persist()


def library_tree(spec: JoinSpec, features: list[Feature], label: Feature, depth: int = 4, boosted: bool = False, rows: DataFrame | None = None):
    """rows: the joined rows, if they are held already."""
    from pyspark.ml.regression import DecisionTreeRegressor, GBTRegressor

    joined = naive_join(spec, [*features, label]).persist() if rows is None else rows
    kind = GBTRegressor(labelCol=label.name, maxIter=1, maxDepth=depth, seed=1) if boosted else DecisionTreeRegressor(labelCol=label.name, maxDepth=depth, maxBins=256)
    try:
        return kind.fit(assembled(joined, [f.name for f in features]))
    finally:
        if rows is None:
            joined.unpersist()


def numpy_lstsq(spec: JoinSpec, features: list[Feature], label: Feature) -> linear.LinearModel:
    """numpy's least squares on all joined rows, each as often as its multiplicity.  A task keeps the triangular factor of its
    rows by Householder's QR, which has the same least squares; the driver takes these a task at a time."""
    names = [f.name for f in (*features, label)]
    n = len(names) + 1

    def run(batches):
        r = np.zeros((0, n))
        for b in batches:
            x = np.column_stack([np.ones(b.num_rows), *[np.asarray(b.column(c), float) for c in names]])
            r = np.linalg.qr(np.vstack([r, x * np.sqrt(np.asarray(b.column("__mult"), float))[:, None]]), mode="r")
        yield pa.RecordBatch.from_arrays([pa.array(r.tolist(), pa.list_(pa.float64()))], ["r"])

    rows = naive_join(spec, [*features, label]).select(*[F.col(c).cast("double").alias(c) for c in names], F.col("__mult").cast("double").alias("__mult"))
    r = np.zeros((0, n))
    for got in rows.mapInArrow(run, "r array<double>").toLocalIterator():
        r = np.vstack([r, [got.r]])
        if len(r) > 64 * n:
            r = np.linalg.qr(r, mode="r")
    scale = np.abs(r[:, :-1]).max(0, initial=0)
    scale = np.where(scale > 0, scale, 1.0)
    return linear.LinearModel(["1", *names[:-1]], np.linalg.lstsq(r[:, :-1] / scale, r[:, -1], rcond=None)[0] / scale)


def frame_totals(df: DataFrame, a: str, b: str) -> DataFrame:
    """(n, total) of all rows, by data frames of the library: a task holds one batch of rows as a frame, and their sums are added."""

    def run(frames):
        for pdf in frames:
            yield pd.DataFrame({"n": [len(pdf)], "total": [float((pdf[a] * pdf[b]).sum())]})

    return df.select(a, b).mapInPandas(run, "n long, total double").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.sum("total").alias("total"))


def dense_copy(spec: JoinSpec, features: list[Feature], budget_bytes: int) -> np.ndarray:
    """A dense matrix and its transposed copy on the driver: fails by memory where the other ways do not."""
    n = int(naive_join(spec, features).count())
    if 2 * n * (len(features) + 1) * 8 > budget_bytes:
        raise MemoryBudgetExceeded(f"{2 * n * (len(features) + 1) * 8} bytes, budget {budget_bytes}")
    x = materialise_pandas(spec, features, n)[[f.name for f in features]].to_numpy(float)
    return np.ascontiguousarray(x.T) @ x


def sgd_from_csv(spark: SparkSession, spec: JoinSpec, features: list[Feature], label: Feature, path: str, batch_size: int = 100_000) -> linear.LinearModel:
    """The joined rows written once as text, then read in mini-batches."""
    names = [f.name for f in (*features, label)]
    naive_join(spec, [*features, label]).select(*names).write.mode("overwrite").option("header", True).csv(path)
    rows = spark.read.schema(", ".join(f"{n} double" for n in names)).option("header", True).csv(path)
    return linear.sgd(rows, names[:-1], label.name, linear.Scale.of(rows, names), batch_size)


def library_iterations(spec: JoinSpec, features: list[Feature], label: Feature | None, kind: str, rounds: int = 10, clusters: int = 5):
    """A library's own rounds over the stored join: logistic regression on a 0/1 label, or k-means on the features."""
    joined = naive_join(spec, [*features, *([label] if label else [])]).persist()
    try:
        rows = assembled(joined, [f.name for f in features])
        if kind == "logistic":
            from pyspark.ml.classification import LogisticRegression

            return LogisticRegression(labelCol=label.name, maxIter=rounds, regParam=0.0).fit(rows)
        from pyspark.ml.clustering import KMeans

        return KMeans(k=clusters, maxIter=rounds, seed=1).fit(rows)
    finally:
        joined.unpersist()


def closed_form_sql(spark: SparkSession, spec: JoinSpec, feature: Feature, label: Feature) -> DataFrame:
    """In-database closed form: moments and the solution of the two normal equations in one SQL statement."""
    naive_join(spec, [feature, label]).createOrReplaceTempView("relml_joined")
    x, y = feature.name, label.name
    return spark.sql(f"WITH m AS (SELECT sum(__mult) AS n, sum(__mult * {x}) AS sx, sum(__mult * {y}) AS sy, sum(__mult * {x} * {x}) AS sxx, sum(__mult * {x} * {y}) AS sxy FROM relml_joined) SELECT (n * sxy - sx * sy) / (n * sxx - sx * sx) AS slope, (sxx * sy - sx * sxy) / (n * sxx - sx * sx) AS intercept FROM m")


query("baseline_ml_lr")(lambda spark, sf: library_linear(*ds.narrow6(spark, sf, "train")).to_df(spark))
query("baseline_numpy_lstsq")(lambda spark, sf: numpy_lstsq(*ds.narrow6(spark, sf, "train")).to_df(spark))


@query("baseline_ml_tree")
def baseline_tree(spark: SparkSession, sf: str) -> DataFrame:
    m = library_tree(*ds.narrow6(spark, sf, "train"))
    return spark.createDataFrame([(m.numNodes, m.depth)], "nodes int, depth int")


@query("baseline_ml_gbt")
def baseline_gbt(spark: SparkSession, sf: str) -> DataFrame:
    m = library_tree(*ds.narrow6(spark, sf, "train"), boosted=True)
    return spark.createDataFrame([(m.totalNumNodes, m.getNumTrees)], "nodes int, trees int")


_TAX_Y = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey"


@query("baseline_sql_closed_form", f"SELECT {sig_sql('regr_slope(l_quantity, l_tax)')} AS slope, {sig_sql('regr_intercept(l_quantity, l_tax)')} AS intercept FROM {_TAX_Y}")
def baseline_sql(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf)
    got = closed_form_sql(spark, spec, next(f for f in fs if f.name == "l_tax"), y)
    return got.select(sig(F.col("slope")).alias("slope"), sig(F.col("intercept")).alias("intercept"))


@query("baseline_ml_logistic")
def baseline_logistic(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, _ = ds.narrow6(spark, sf)
    m = library_iterations(spec, fs, Feature("returned", "lineitem", "case when l_returnflag = 'R' then 1 else 0 end"), "logistic")
    return spark.createDataFrame([("1", float(m.intercept)), *[(f.name, float(c)) for f, c in zip(fs, m.coefficients)]], "feature string, theta double")


@query("baseline_ml_kmeans")
def baseline_kmeans(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, _ = ds.narrow6(spark, sf)
    m = library_iterations(spec, fs, None, "kmeans")
    return spark.createDataFrame([(k, f.name, float(v)) for k, c in enumerate(m.clusterCenters()) for f, v in zip(fs, c)], "cluster int, feature string, value double")


@query("baseline_pandas_frame", f"SELECT CAST(count(*) AS BIGINT) AS n, {sig_sql('sum(l_quantity * l_tax)')} AS total FROM {_TAX_Y}")
def baseline_pandas(spark: SparkSession, sf: str) -> DataFrame:
    """The joined rows as a data-frame library works on them, a frame for each batch of rows."""
    spec, fs, y = ds.narrow6(spark, sf)
    return frame_totals(naive_join(spec, [*fs, y]), y.name, "l_tax").select("n", sig(F.col("total")).alias("total"))


#: Bytes that the dense copy may take on the driver.  It needs two copies of rows x 8 values of 8 bytes.
DENSE_BUDGET = 16 << 20


@query("baseline_memory_failure", f"SELECT dataset, CASE WHEN 2 * n * w * 8 > {DENSE_BUDGET} THEN 'MemoryBudgetExceeded' ELSE 'ok' END AS status FROM (SELECT 'quarter' AS dataset, count(*) AS n, 8 AS w FROM {_TAX_Y} WHERE l_orderkey % 4 = 0 UNION ALL SELECT 'full', count(*), 8 FROM {_TAX_Y} UNION ALL SELECT 'full, 35 features', count(*), 37 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey)")
def baseline_failure(spark: SparkSession, sf: str) -> DataFrame:
    """Small inputs pass, larger ones do not fit: the library's failure by a transposed copy."""
    rows = []
    for name, (spec, fs, y) in (("quarter", ds.narrow6(spark, sf, "quarter")), ("full", ds.narrow6(spark, sf)), ("full, 35 features", ds.wide35(spark, sf))):
        try:
            dense_copy(spec, [*fs, y], DENSE_BUDGET)
            rows.append((name, "ok"))
        except MemoryBudgetExceeded as e:
            rows.append((name, type(e).__name__))
    return spark.createDataFrame(rows, "dataset string, status string")
