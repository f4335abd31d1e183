"""Minimax contiguous partition of ordered atomic groups into shards, in native DataFrame operations.

A group is the rows of equal text, atomic, ordered by the 64-bit hash of the text (texts with equal hashes share a group).
The least capacity with which a greedy sweep needs no more than the given shards is found by binary search.  The driver
never sees all groups: it holds ranges of hash values with their sizes.  A first histogram of 4096 ranges bounds the
capacity between the least that the ranges allow and the most that they need; the ranges in which a cut of any capacity
between can lie are split again, until each is one group or the bounds meet.  A row's shard then follows from its hash
and the 7 cuts, without a join.

Slots number a shard's rows without gaps.  They are counted in salted parts, so the hottest group is split.
Null text has no bytes; a row's size is its bytes plus 1.  Repeated rows take a slot each.  An empty table gives no rows.
"""

from __future__ import annotations

import bisect
import itertools
import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

SPLIT = 12
HALF = 1 << 63


def greedy(sizes: list[int], capacity: int) -> list[int]:
    """Index after the last piece of each shard but the last, when pieces are taken in order while they fit."""
    cuts, load = [], 0
    for k, s in enumerate(sizes):
        if load and load + s > capacity:
            cuts.append(k)
            load = 0
        load += s
    return cuts


def least_capacity(sizes: list[int], shards: int) -> int:
    """Smallest capacity for which greedy() makes at most `shards` shards."""
    low, high = max([1, math.ceil(sum(sizes) / shards), *sizes]), max(1, sum(sizes))
    while low < high:
        mid = (low + high) // 2
        if len(greedy(sizes, mid)) < shards:
            high = mid
        else:
            low = mid + 1
    return low


def _cut_spans(ranges: list[tuple[int, int, int, int, int]], shards: int, low: int, high: int) -> set[int]:
    """Indexes of the ranges in which, for some capacity between low and high, a cut can lie.  A cut is the last border
    of groups within reach, so it is not below the start of the range in which the reach ends."""
    ends = list(itertools.accumulate(r[2] for r in ranges))
    first, last, out = 0, 0, set()
    for _ in range(shards - 1):
        reach = first + low
        i = min(bisect.bisect_left(ends, reach), len(ends) - 1)
        first = max(ends[i] - ranges[i][2], min(reach, ends[i]) - ranges[i][3])
        last = min(last + high, ends[-1])
        lo, hi = bisect.bisect_left(ends, first), bisect.bisect_left(ends, last)
        out |= {k for k in range(lo, min(hi, len(ends) - 1) + 1) if ranges[k][4] > 1}
    return out


def find_cuts(groups: DataFrame, shards: int) -> list[int]:
    """First hash of each shard but the first.  groups: (h long, size long), one row per group, settled."""

    def histogram(spans: list[tuple[int, int, int]]) -> list[tuple[int, int, int, int, int]]:
        """(from, width in bits, size, largest group, groups) of the parts of each span (from, width in bits, part width)."""
        out = []
        for width, step in sorted({s[1:] for s in spans}):
            rows = groups
            if width < 64:
                rows = groups.where(F.shiftright("h", width).isin([s[0] >> width for s in spans if s[1] == width]))
            got = rows.groupBy(F.shiftright("h", step).alias("p")).agg(F.sum("size").alias("s"), F.max("size").alias("m"), F.count("*").alias("n")).collect()
            out += [(r.p << step, step, r.s, r.m, r.n) for r in got]
        return out

    ranges = sorted(histogram([(-HALF, 64, 64 - SPLIT)]))
    while ranges:
        sizes = [r[2] for r in ranges]
        low = max([1, math.ceil(sum(sizes) / shards), *(r[3] for r in ranges)])
        high = max(low, least_capacity(sizes, shards))
        open_ = sorted(_cut_spans(ranges, shards, low, high)) if high > low else []
        if not open_:
            break
        chosen = [ranges[i] for i in open_]
        split = histogram([(r[0], r[1], max(0, r[1] - SPLIT)) for r in chosen])
        keep = set(open_)
        ranges = sorted([r for i, r in enumerate(ranges) if i not in keep] + split)
    capacity = least_capacity([r[2] for r in ranges], shards)
    return [ranges[k][0] for k in greedy([r[2] for r in ranges], capacity)]


def shard_of(h: Column, cuts: list[int]) -> Column:
    out = F.lit(0)
    for c in cuts:
        out = out + (h >= F.lit(c)).cast("int")
    return out


def shard_documents(docs: DataFrame, shards: int = 8, id_col: str = "doc_id", text_col: str = "text", salt_rows: int = 50_000) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) of each row; law `bytes`."""
    raw = F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    rows = common.settle(docs.select(F.col(id_col).cast("long").alias("doc_id"), (F.coalesce(F.octet_length(text_col), F.lit(0)) + 1).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"), F.xxhash64(raw).alias("h")), "sizes")
    groups = common.settle(rows.groupBy("h").agg(F.sum("size").alias("size")), "groups")
    cuts = find_cuts(groups, shards)
    parts = max(8, math.ceil(rows.count() / salt_rows))
    dealt = rows.select("doc_id", "size", "text_crc32", shard_of(F.col("h"), cuts).alias("shard"), F.pmod(F.xxhash64("doc_id", "h"), F.lit(parts)).cast("int").alias("part"))
    counts = dealt.groupBy("shard", "part").count()
    before = F.coalesce(F.sum("count").over(Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    base = counts.select("shard", "part", before.alias("base"))
    order = Window.partitionBy("shard", "part").orderBy("doc_id", "text_crc32")
    out = dealt.withColumn("k", F.row_number().over(order)).join(base, ["shard", "part"])
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("base") + F.col("k") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
