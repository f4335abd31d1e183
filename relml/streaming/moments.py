"""Moments of a stream: they add up, so windows and micro-batches are sums of sums.

The batch form of a window query and its streaming form are one function over a DataFrame that may be streaming."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import query, sig, sig_sql
from ..layout import scratch_dir
from ..moments import MomentMatrix
from ..sources.io import load


def events(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_moments(df: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, n, s1, s2) of value by window; late rows beyond the watermark are left out of a stream."""
    rows = df.withWatermark("ts", late) if df.isStreaming else df
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return rows.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("s1"), F.sum(F.col("value") * F.col("value")).alias("s2")).select(F.col("w.start").alias("start"), "n", "s1", "s2")


def session_moments(df: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    rows = df.withWatermark("ts", late) if df.isStreaming else df
    return rows.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("s1")).select("user_id", F.col("w.start").alias("start"), "n", "s1")


class StreamedMoments:
    """foreachBatch sink that merges each micro-batch's moments into a stored matrix.  A batch number is merged once, so
    a batch that runs again after a failure changes nothing."""

    def __init__(self, path: str, columns: list[str]):
        self.path, self.columns = path, columns

    def __call__(self, df: DataFrame, batch: int) -> None:
        spark, names = df.sparkSession, ["1", *self.columns]
        cols = [F.lit(1.0), *[F.col(c).cast("double") for c in self.columns]]
        pairs = [(i, j) for i in range(len(names)) for j in range(i, len(names))]
        sums = df.agg(*[F.sum(cols[i] * cols[j]) for i, j in pairs]).first()
        rows = [(int(batch), i, j, float(v or 0)) for (i, j), v in zip(pairs, sums)]
        spark.createDataFrame(rows, "batch long, i int, j int, v double").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/batch={batch:012d}")

    def matrix(self, spark: SparkSession) -> MomentMatrix:
        import numpy as np

        n = len(self.columns) + 1
        out = np.zeros((n, n))
        for r in spark.read.parquet(f"{self.path}/batch=*").groupBy("i", "j").agg(F.sum("v").alias("v")).collect():
            out[r.i, r.j] = out[r.j, r.i] = r.v
        return MomentMatrix(["1", *self.columns], out, {})


def run_available(stream: DataFrame, sink, checkpoint: str) -> None:
    q = stream.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def event_stream(spark: SparkSession, sf: str) -> DataFrame:
    """The events table as a stream of files; a pattern, as the path may be one file or a folder."""
    schema = load(spark, sf, "events").schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", 4).parquet(f"{sf}/[e]vents.parquet")
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def answer(df: DataFrame, keys: list[str], mode: str = "complete") -> DataFrame:
    """Run a streaming query over all input that is there, and read its result.  Each micro-batch's rows are stored under its
    number, so a batch that runs again replaces itself; the last row of each key counts."""
    spark, path = df.sparkSession, scratch_dir(df.sparkSession, "stream")

    def keep(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/out/batch={int(batch):09d}")

    q = df.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    rows = spark.read.schema(f"{_ddl(df)}, batch long").parquet(f"{path}/out")
    others = [c for c in df.columns if c not in keys]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*others), "batch").alias("x")).select(*keys, "x.*")


def _ddl(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)


def user_state(df: DataFrame, late: str = "1 hour") -> DataFrame:
    """(user_id, n, s1, late) in a state of three numbers and a time per user: rows older than `late` before the latest time of
    their user's earlier batches are counted and left out."""
    import pandas as pd

    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    gap = pd.Timedelta(late)

    def step(key, parts, state: GroupState):
        n, s1, gone, latest = state.get if state.exists else (0, 0.0, 0, None)
        limit = None if latest is None else pd.Timestamp(latest, unit="us") - gap
        for part in parts:
            ts = pd.to_datetime(part["ts"]).dt.tz_localize(None)
            on = part["value"] if limit is None else part["value"][ts >= limit]
            n, s1, gone = n + len(on), s1 + float(on.sum()), gone + len(part) - len(on)
            newest = int(ts.max().value // 1000)
            latest = newest if latest is None else max(latest, newest)
        state.update((n, s1, gone, latest))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "s1": [s1], "late": [gone]})

    return df.select("user_id", "ts", "value").groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, s1 double, late long", "n long, s1 double, late long, latest long", "update", GroupStateTimeout.NoTimeout)


def _epoch(c):
    return F.unix_seconds(c)


@query("stream_tumbling_moments", f"SELECT CAST(epoch(time_bucket(INTERVAL 1 DAY, ts)) AS BIGINT) AS start, CAST(count(*) AS BIGINT) AS n, {sig_sql('sum(value)')} AS s1, {sig_sql('sum(value * value)')} AS s2 FROM events GROUP BY 1")
def tumbling(spark: SparkSession, sf: str) -> DataFrame:
    got = answer(windowed_moments(event_stream(spark, sf), "1 day"), ["start"])
    return got.select(_epoch("start").alias("start"), "n", sig(F.col("s1")).alias("s1"), sig(F.col("s2")).alias("s2"))


@query("stream_sliding_moments", f"SELECT CAST(epoch(time_bucket(INTERVAL 12 HOUR, ts)) - 43200 * k AS BIGINT) AS start, CAST(count(*) AS BIGINT) AS n, {sig_sql('sum(value)')} AS s1 FROM events, (SELECT range AS k FROM range(2)) GROUP BY 1")
def sliding(spark: SparkSession, sf: str) -> DataFrame:
    got = answer(windowed_moments(event_stream(spark, sf), "1 day", "12 hours"), ["start"])
    return got.select(_epoch("start").alias("start"), "n", sig(F.col("s1")).alias("s1"))


@query("stream_session_moments", "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(f) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM e) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, CAST(count(*) AS BIGINT) AS n FROM s GROUP BY user_id, g")
def sessions(spark: SparkSession, sf: str) -> DataFrame:
    got = answer(session_moments(event_stream(spark, sf), "6 hours"), ["user_id", "start"])
    return got.select("user_id", _epoch("start").alias("start"), "n")


@query("stream_late_data", f"WITH e AS (SELECT value, coalesce(ts < max(ts) OVER (PARTITION BY user_id % 16 ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) - INTERVAL 1 HOUR, false) AS late FROM events) SELECT late, CAST(count(*) AS BIGINT) AS n, {sig_sql('sum(value)')} AS s1 FROM e GROUP BY 1")
def late_data(spark: SparkSession, sf: str) -> DataFrame:
    """Rows that a watermark of one hour behind the latest time so far, in order of event_id, would leave out."""
    df = events(spark, sf)
    w = Window.partitionBy(F.pmod("user_id", F.lit(16))).orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    late = F.col("ts") < F.max("ts").over(w) - F.expr("interval 1 hour")
    return df.withColumn("late", F.coalesce(late, F.lit(False))).groupBy("late").agg(F.count("*").alias("n"), sig(F.sum("value")).alias("s1"))


@query("stream_static_join", f"SELECT c_nationkey, CAST(epoch(time_bucket(INTERVAL 1 DAY, ts)) AS BIGINT) AS start, CAST(count(*) AS BIGINT) AS n, {sig_sql('sum(value * c_acctbal)')} AS vb FROM events JOIN customer ON user_id = c_custkey GROUP BY 1, 2")
def stream_static(spark: SparkSession, sf: str) -> DataFrame:
    """Moments of a stream joined with a dimension that stands still."""
    customers = load(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_acctbal")
    rows = event_stream(spark, sf).withWatermark("ts", "1 hour").join(customers, F.col("user_id") == F.col("c_custkey"))
    sums = rows.groupBy("c_nationkey", F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"), F.sum(F.col("value") * F.col("c_acctbal")).alias("vb"))
    got = answer(sums.select("c_nationkey", F.col("w.start").alias("start"), "n", "vb"), ["c_nationkey", "start"])
    return got.select("c_nationkey", _epoch("start").alias("start"), "n", sig(F.col("vb")).alias("vb"))


@query("stream_user_state", f"SELECT user_id, CAST(count(*) AS BIGINT) AS n, {sig_sql('sum(value) + 1000000')} AS s1 FROM events GROUP BY 1")
def stream_user_state(spark: SparkSession, sf: str) -> DataFrame:
    got = answer(user_state(event_stream(spark, sf), "36500 days"), ["user_id"], "update")
    return got.select("user_id", "n", sig(F.col("s1") + 1_000_000).alias("s1"))
