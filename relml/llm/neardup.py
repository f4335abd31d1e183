"""Near-duplicates by Jaccard similarity of word shingles, 0.8 or more.

Texts of equal shingle sets are one node.  Least values under 384 hashes are cut into 64 bands of 6; nodes that share a band
are candidates, which a pair at 0.8 misses with a chance of 4e-9.  Candidates are linked as stars and gathered by component;
within one, shared rare shingles find the pairs and each link is settled on the exact sets.  Members that are linked already
are not compared, so a group of near copies costs about its size.  A component of candidates is worked out in one task.

With `fingerprints` the links of SimHash, found at its anchors, give candidates as well, which the exact check follows.

Texts that are null, empty or without words are one node.  Rows without an id stay, and link others like any row.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, simhash
from .components import connected_components
from .simhash import shingles

SHINGLE, BANDS, ROWS = 5, 64, 6
_RNG = np.random.default_rng(19)
_FLIP, _TIMES, _MIX = (_RNG.integers(0, 1 << 63, (BANDS * ROWS, 1), np.uint64) << np.uint64(1) | np.uint64(1) for _ in range(3))


def shingle_set(text: str) -> np.ndarray:
    return np.unique(shingles(text, SHINGLE).astype(np.uint64))


def node_of(own: np.ndarray) -> int:
    from xxhash import xxh64_intdigest

    return int(np.uint64(xxh64_intdigest(own.tobytes(), 43)).view(np.int64))


def band_keys(own: np.ndarray) -> np.ndarray:
    """One key a band; none for an empty set."""
    if not len(own):
        return np.zeros(0, np.int64)
    least = np.full(len(_FLIP), np.iinfo(np.uint64).max, np.uint64)
    for lo in range(0, len(own), 512):
        least = np.minimum(least, ((own[lo : lo + 512] ^ _FLIP) * _TIMES).min(1))
    mixed = (least >> np.uint64(7) ^ least) * _MIX[:, 0]
    return mixed.reshape(BANDS, ROWS).sum(1, dtype=np.uint64).view(np.int64)


def linked(sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """Pairs of similarity 0.8 or more that span all components of such pairs.  No set is empty."""
    sizes = [len(s) for s in sets]
    _, at, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    rank = np.empty(len(count), np.int64)
    rank[np.argsort(count, kind="stable")] = np.arange(len(count))
    tokens = [np.sort(t) for t in np.split(rank[at], np.cumsum(sizes)[:-1])]
    up, index, out = list(range(len(sets))), {}, []

    def top(k: int) -> int:
        while up[k] != k:
            up[k] = up[up[k]]
            k = up[k]
        return k

    for x in sorted(range(len(sets)), key=sizes.__getitem__):
        # of two similar sets the rarest fifth and one more share a shingle
        tried, first = set(), tokens[x][: sizes[x] - -(-4 * sizes[x] // 5) + 1].tolist()
        for t in first:
            held = index.setdefault(t, {})  # component -> members
            for r in [*held]:
                if top(r) != r:
                    members = held.pop(r)
                    held.setdefault(top(r), []).extend(members)
            for members in [*held.values()]:
                for y in members:
                    if top(y) == top(x):
                        break
                    if y in tried:
                        continue
                    tried.add(y)
                    if 5 * sizes[y] >= 4 * sizes[x] and 9 * len(np.intersect1d(tokens[x], tokens[y], assume_unique=True)) >= 4 * (sizes[x] + sizes[y]):
                        up[max(top(x), top(y))] = min(top(x), top(y))
                        out.append((x, y))
                        break
        for t in first:
            index[t].setdefault(top(x), []).append(x)
    return out


def _sketches(docs: DataFrame, id_col: str, text_col: str, fingerprints: bool = False) -> DataFrame:
    """(doc_id, node, bands) of each row, and fp, its SimHash fingerprint, if asked for."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = common.texts_of(batch, "t")
            sets = [shingle_set(t) for t in texts]
            out = [batch.column("i"), pa.array([node_of(s) for s in sets], pa.int64()), pa.array([band_keys(s) for s in sets], pa.list_(pa.int64()))]
            if fingerprints:
                out.append(pa.array(np.array([simhash.fingerprint(t) for t in texts], np.uint64).view(np.int64)))
            return pa.RecordBatch.from_arrays(out, ["doc_id", "node", "bands", "fp"][: len(out)])

        return step

    return common.map_batches(docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")), make, "doc_id long, node long, bands array<long>" + ", fp long" * fingerprints, rows=1024)


def _stars(nodes: DataFrame) -> DataFrame:
    """(a, b): each node of a band with the band's first."""

    def meet(batches):
        key = first = None
        for batch in batches:
            k, node = np.array(batch.column("k")), np.array(batch.column("node"))
            if not len(k):
                continue
            new = np.append(key is None or k[0] != key, k[1:] != k[:-1])
            at = np.maximum.accumulate(np.where(new, np.arange(len(k)), -1))
            head = np.where(at >= 0, node[at], node[0] if first is None else first)
            key, first = k[-1], head[-1]
            yield pa.RecordBatch.from_arrays([pa.array(head[~new]), pa.array(node[~new])], ["a", "b"])

    spread = nodes.select(F.explode("bands").alias("k"), "node")
    return spread.repartition("k").sortWithinPartitions("k").mapInArrow(meet, "a long, b long")


def _verified(texts: DataFrame) -> DataFrame:
    """(a, b): links among the nodes of each root.  texts: (root, node, t)."""

    def settle(batches):
        root, held = None, {}

        def links():
            nodes = [*held]
            pairs = linked([held[n] for n in nodes]) if len(nodes) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([nodes[i] for i, _ in pairs], pa.int64()), pa.array([nodes[j] for _, j in pairs], pa.int64())], ["a", "b"])

        for batch in batches:
            for r, n, t in zip(batch.column("root").to_pylist(), batch.column("node").to_pylist(), common.texts_of(batch, "t")):
                if r != root:
                    if held:
                        yield links()
                    root, held = r, {}
                own = shingle_set(t)
                if node_of(own) == n:  # rows may share an id
                    held[n] = own
        if held:
            yield links()
        common.give_back()

    return texts.repartition("root").sortWithinPartitions("root").mapInArrow(settle, "a long, b long")


def _fingerprint_links(rows: DataFrame) -> DataFrame:
    """(a, b): enough links to connect the nodes of rows whose fingerprints SimHash links."""
    held = rows.select("fp", "node").distinct()
    firsts = common.settle(held.groupBy("fp").agg(F.min("node").alias("first")), "fingerprints")
    near = simhash.links(firsts.select("fp"))
    for end in ("a", "b"):
        near = near.join(firsts.select(F.col("fp").alias(end), F.col("first").alias(f"{end}2")), end)
    return near.select(F.col("a2").alias("a"), F.col("b2").alias("b")).union(held.join(firsts, "fp").select("first", "node").where("first <> node"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", fingerprints: bool = False) -> DataFrame:
    """(doc_id, component_id) of each row; component_id: the least id of the rows linked to it."""
    rows = common.settle(_sketches(docs, id_col, text_col, fingerprints), "sketches")
    nodes = common.settle(rows.groupBy("node").agg(F.min("doc_id").alias("least"), F.first("bands").alias("bands")), "nodes")
    stars = _stars(nodes)
    roots = common.settle(connected_components(stars.union(_fingerprint_links(rows)) if fingerprints else stars), "candidates")
    near = nodes.select("node", "least").join(roots, "node")
    texts = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    known = near.where("least is not null").join(texts, F.col("least") == F.col("i")).select("root", "node", "t")
    bare = _bare(texts.where("i is null")).join(near.where("least is null"), "node").select("root", "node", "t")
    joined = connected_components(_verified(known.union(bare)))
    placed = nodes.select("node", "least").join(joined, "node", "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    named = placed.join(placed.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("node", "component_id")
    return rows.select("doc_id", "node").join(named, "node").select("doc_id", "component_id")


def _bare(texts: DataFrame) -> DataFrame:
    def make():
        return lambda batch: pa.RecordBatch.from_arrays([pa.array([node_of(shingle_set(t)) for t in common.texts_of(batch, "t")], pa.int64()), batch.column("t")], ["node", "t"])

    return common.map_batches(texts.select("t"), make, "node long, t string")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", fingerprints: bool = False) -> DataFrame:
    """The rows of docs, all columns, whose id is the least of their component; rows without an id stay."""
    extra = near_duplicates(docs, id_col, text_col, fingerprints).where("doc_id <> component_id").select(F.col("doc_id").alias(id_col)).distinct()
    return docs.join(extra, id_col, "left_anti").select(*docs.columns)
