"""User-defined functions: scalar prediction, per-group Gram matrices, pairs of an array."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


def predictor(theta: list[float]):
    """Vectorised linear prediction of columns, the intercept first."""

    @pandas_udf("double")
    def predict(*xs: pd.Series) -> pd.Series:
        out = pd.Series(theta[0], index=xs[0].index)
        for t, x in zip(theta[1:], xs):
            out = out + t * x
        return out

    return predict


def gram_by(df: DataFrame, group: str, columns: list[str]) -> DataFrame:
    """(group, i, j, v) second moments of each group.  Blocks are summed per Arrow batch before any shuffle, so a hot group
    is never gathered."""
    n = len(columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            g = np.array(b.column(0).to_pylist(), object)
            x = np.column_stack([np.asarray(b.column(c), float) for c in columns]) if b.num_rows else np.zeros((0, n))
            keys = list(dict.fromkeys(g))
            blocks = [x[g == k].T @ x[g == k] for k in keys]
            yield pa.RecordBatch.from_arrays([pa.array([k for k in keys for _ in range(n * n)], pa.string()), pa.array(np.tile(np.repeat(np.arange(n), n), len(keys))), pa.array(np.tile(np.arange(n), n * len(keys))), pa.array(np.concatenate([m.ravel() for m in blocks]) if blocks else np.zeros(0))], ["g", "i", "j", "v"])

    rows = df.select(F.col(group).cast("string").alias("g"), *[F.col(c).cast("double").alias(c) for c in columns])
    return rows.mapInArrow(run, "g string, i long, j long, v double").groupBy("g", "i", "j").agg(F.sum("v").alias("v"))


@udtf(returnType="i int, j int, value double")
class ExplodePairs:
    """Products of all pairs i <= j of an array."""

    def eval(self, xs):
        for i, a in enumerate(xs or []):
            for j in range(i, len(xs)):
                yield i, j, float(a) * float(xs[j])
