"""Connected components of a link table by alternating star steps; nothing is gathered on the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def _key(edges: DataFrame) -> tuple:
    r = edges.agg(F.count("*"), F.sum(F.pmod(F.xxhash64("a", "b"), F.lit(1 << 31)))).first()
    return r[0], r[1]


def connected_components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root) of each node that has a link; root is the least node of its component.  links: (a long, b long).

    A round joins each node's neighbours to its least one, first the greater neighbours, then the lesser.  Minima are
    combined before their shuffle; a hub's links are a skewed join, which adaptive execution splits."""
    edges = common.settle(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    seen = _key(edges)
    for _ in range(most_rounds):
        if not seen[0]:
            break
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(low.select("a", F.col("m").alias("b"))).distinct()
        new = common.settle(small, "links")
        now = _key(new)
        common.discard(edges)
        edges = new
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root")).union(edges.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
