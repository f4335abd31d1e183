"""SimHash near-duplicates with a covering code as anchors.

Fingerprints within 3 of 64 bits agree to within one bit in one of their two halves of 32.  The anchors of a half are the
codewords of the perfect single-error code of length 31, with one free bit beside it: each half lies within distance 1 of
its nearest anchor, its home.  A fingerprint goes to every anchor within covering radius 1 plus threshold 1, 17 or fewer;
two fingerprints that agree to within one bit in a half therefore meet at the home of each.  At an anchor, in a run of a
sorted partition, home members are compared with all members over all 64 bits; a run gives a forest of links, not its pairs.
An anchor with many members is cut: each part compares its share of the home members with all, so that no task has them all.

Equal fingerprints are one node, so copies are never paired.  Components are found by distributed star steps.

Null and empty texts, and texts without words, have fingerprint zero and link like any other.  Rows that share an id take
part as rows; a null id is never the least id unless all of the component's are null.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common
from .components import connected_components

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_WORDS = re.compile(rb"[^\x20\x09-\x0D]+")
THRESHOLD = 3
BLOCK = 2048


def shingles(text: str, shingle: int) -> np.ndarray:
    """Hashes of the runs of words, in order; of all words if there are fewer."""
    from xxhash import xxh64_intdigest

    words = _WORDS.findall(text.encode().translate(_LOWER))
    if not words:
        return np.zeros(0, ">u8")
    rows = zip(*(words[k:] for k in range(shingle))) if len(words) > shingle else [words]
    return np.array([xxh64_intdigest(x, 42) for x in map(b" ".join, rows)], ">u8")


def fingerprint(text: str, shingle: int = 3) -> int:
    h = shingles(text, shingle)
    if not len(h):
        return 0
    ones = np.zeros(64, np.int64)
    for lo in range(0, len(h), 65536):
        ones += np.unpackbits(h[lo : lo + 65536].view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(h)).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp long, signed)."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = np.array([fingerprint(t, shingle) for t in common.texts_of(batch, "t")], np.uint64)
            return pa.RecordBatch.from_arrays([batch.column("i"), pa.array(got.view(np.int64))], ["doc_id", "fp"])

        return step

    return common.map_batches(docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")), make, "doc_id long, fp long")


def _syndromes() -> np.ndarray:
    """XOR of the places 1 to 31 of the set bits, for each byte of the word."""
    out = np.zeros((4, 256), np.uint32)
    for byte in range(4):
        for value in range(256):
            for bit in range(8):
                if value >> bit & 1 and byte * 8 + bit < 31:
                    out[byte, value] ^= byte * 8 + bit + 1
    return out


_SYNDROME = _syndromes()
#: For each syndrome the flips that lead to the anchors within distance 2, the home first.
_FLIPS = [[0, 1 << 31]] + [[1 << (s - 1), 1 << (s - 1) | 1 << 31] + [1 << (i - 1) | 1 << ((i ^ s) - 1) for i in range(1, 32) if i < i ^ s] for s in range(1, 32)]


def anchors(half: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, anchor, is home) for 32-bit words."""
    b = half.astype("<u4").view(np.uint8).reshape(-1, 4)
    s = _SYNDROME[0, b[:, 0]] ^ _SYNDROME[1, b[:, 1]] ^ _SYNDROME[2, b[:, 2]] ^ _SYNDROME[3, b[:, 3]]
    rows, keys, home = [], [], []
    for v in np.unique(s):
        at = np.flatnonzero(s == v)
        flips = np.array(_FLIPS[v], np.uint32)
        rows.append(np.repeat(at, len(flips)))
        keys.append((half[at].astype(np.uint32)[:, None] ^ flips[None]).ravel())
        home.append(np.tile(np.arange(len(flips)) == 0, len(at)))
    return np.concatenate(rows), np.concatenate(keys), np.concatenate(home)


def forest(fp: np.ndarray, home: np.ndarray, threshold: int = THRESHOLD) -> list[tuple[int, int]]:
    """Links that span the components of the members of one anchor; only pairs with a home member count."""
    n = len(fp)
    up = np.arange(n)

    def top(k: int) -> int:
        while up[k] != k:
            up[k] = up[up[k]]
            k = up[k]
        return k

    out = []
    for lo in range(0, n, BLOCK):
        own = lo + np.flatnonzero(home[lo : lo + BLOCK])
        for to in range(0, n, BLOCK):
            near = np.bitwise_count(fp[own][:, None] ^ fp[to : to + BLOCK][None]) <= threshold
            i, j = np.nonzero(near)
            for a, b in zip(own[i].tolist(), (j + to).tolist()):
                if a != b and (x := top(a)) != (y := top(b)):
                    up[max(x, y)] = min(x, y)
                    out.append((a, b))
    return out


def links(nodes: DataFrame, most: int = 4 * BLOCK) -> DataFrame:
    """(a, b) pairs of distinct fingerprints within the threshold, enough to connect all that are.  nodes: (fp).  most: members
    of an anchor that one task compares its home members with before it is cut."""

    def spread(batches):
        for batch in batches:
            fp = np.array(batch.column("fp")).astype(np.int64).view(np.uint64)
            if not len(fp):
                continue
            for side in (0, 1):
                half = (fp >> np.uint64(32 * side)).astype(np.uint32)
                r, k, home = anchors(half)
                key = k.astype(np.int64) << 1 | side
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(fp[r].view(np.int64)), pa.array(home)], ["k", "fp", "home"])

    def meet(batches):
        tail = None
        for batch in batches:
            k, fp, home = np.array(batch.column("k")), np.array(batch.column("fp")).view(np.uint64), np.array(batch.column("home"))
            if tail is not None:
                k, fp, home = np.concatenate([tail[0], k]), np.concatenate([tail[1], fp]), np.concatenate([tail[2], home])
            if not len(k):
                continue
            last = int(np.searchsorted(k, k[-1]))  # its run may go on in the next batch
            tail = k[last:], fp[last:], home[last:]
            yield found(k[:last], fp[:last], home[:last])
        if tail is not None:
            yield found(*tail)

    def found(k, fp, home):
        a, b = [], []
        if len(k):
            starts = np.flatnonzero(np.append(True, k[1:] != k[:-1]))
            sizes = np.diff(np.append(starts, len(k)))
            two = starts[sizes == 2]
            near = two[(np.bitwise_count(fp[two] ^ fp[two + 1]) <= THRESHOLD) & (home[two] | home[two + 1])] if len(two) else two
            a.append(fp[near])
            b.append(fp[near + 1])
            for lo, n in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist()):
                if home[lo : lo + n].any():
                    got = forest(fp[lo : lo + n], home[lo : lo + n])
                    a.append(fp[[lo + i for i, _ in got]] if got else fp[:0])
                    b.append(fp[[lo + j for _, j in got]] if got else fp[:0])
        empty = np.zeros(0, np.uint64)
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([empty, *a]).view(np.int64)), pa.array(np.concatenate([empty, *b]).view(np.int64))], ["a", "b"])

    rows = nodes.select("fp").mapInArrow(spread, "k long, fp long, home boolean")
    crowd = common.settle(rows.groupBy("k").count().where(F.col("count") > most).select("k", F.ceil(F.col("count") / most).cast("int").alias("parts")), "crowds")
    if crowd.take(1):
        both = rows.join(crowd.hint("merge"), "k", "left").select("k", "fp", "home", F.coalesce("parts", F.lit(1)).alias("parts"))
        part = F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part")
        rows = both.select("k", "fp", "home", "parts", part).select("k", "part", "fp", (F.col("home") & (F.pmod(F.xxhash64("fp"), "parts") == F.col("part"))).alias("home"))
        rows = rows.select(F.xxhash64("k", "part").alias("k"), "fp", "home")  # runs whose hashes meet are one: links are checked anyway
    return rows.repartition("k").sortWithinPartitions("k").mapInArrow(meet, "a long, b long")


def hex_of(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """(doc_id, fingerprint, component_id) of each row."""
    rows = common.settle(fingerprints(docs, shingle, id_col, text_col), "fingerprints")
    nodes = common.settle(rows.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    roots = connected_components(links(nodes))
    placed = nodes.join(roots, nodes.fp == roots.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    least = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    named = common.settle(placed.join(least, "root").select("fp", "component_id"), "named")
    return rows.join(named, "fp").select("doc_id", hex_of(F.col("fp")).alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs, all columns, whose id is the least of their component; rows without an id stay."""
    extra = near_duplicates(docs, id_col, text_col).where("doc_id <> component_id").select(F.col("doc_id").alias(id_col)).distinct()
    return docs.join(extra, id_col, "left_anti").select(*docs.columns)
