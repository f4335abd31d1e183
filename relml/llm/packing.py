"""Vector bin packing of examples under limits on tokens, segments and loss-bearing tokens.

Dot-product heuristic: a bin is filled by the item that fits and whose demands, weighed by the capacity that is left,
give the largest product (first such item on ties).  Where cutting is allowed, a bin that no whole item fits is filled by
the front of the largest item, whose rest goes back to the pool; what is left when a task's rows end goes into sequences
whose lengths are powers of two, so it needs no padding.

A task packs its own rows in windows of bounded size, so no row moves between tasks and no group is gathered: a hot
source or a group of copies is just rows.  Sequence ids are the task's partition number and a running number.

Null and empty texts have one id, the end id.  Repeated rows are packed once each.  An empty table gives no rows.
"""

from __future__ import annotations

import json
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

_ODD = re.compile("[^\t\n\r -~¡-ɏ‐-‧]|[ª²³¹º¼-¾]")
_UNEVEN = ("  ", " \n", "\n ", " \t", "\t ", " \r", "\r ")


class ByteBpe:
    """Ids of the byte-level tokenizer file as uint32 bytes; chunks between single spaces are kept, up to a number of bytes."""

    def __init__(self, file: str, cache: int = common.CACHE_BYTES):
        import tiktoken
        from public_tokenizers import PATTERN

        from .bpe import byte_alphabet

        spec = json.load(open(file, encoding="utf-8"))
        back = {c: b for b, c in byte_alphabet().items()}
        ranks = {bytes(back[c] for c in t): i for t, i in spec["model"]["vocab"].items() if all(c in back for c in t)}
        self.special = [a["content"] for a in spec["added_tokens"]]
        for s in self.special:
            ranks.pop(s.encode(), None)
        self.core = tiktoken.Encoding("byte-bpe", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})._core_bpe
        self.file = file
        self.sizes = np.zeros(max(ranks.values()) + 2, np.int64)
        for token, i in ranks.items():
            self.sizes[i] = len(token)
        self.known = common.Known(limit=cache)
        self.heads = common.Known(self.direct, cache // 4)
        self._exact = None

    def direct(self, text: str) -> bytes:
        return np.array(self.core.encode_ordinary(text), "<u4").tobytes()

    def exact(self, text: str) -> bytes:
        """By the library: for texts with its special strings or characters whose class differs between Unicode tables."""
        if self._exact is None:
            from tokenizers import Tokenizer

            self._exact = Tokenizer.from_file(self.file)
            self._exact.no_truncation()
            self._exact.no_padding()
        return np.array(self._exact.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def encode(self, text: str) -> bytes:
        return self.encode_batch([text])[0]

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """A space between two words is always a cut, and none of the chunks that it starts depends on its neighbours."""
        out: list = []
        known = self.known
        for text in texts:
            if _ODD.search(text) or any(s in text for s in self.special):
                out.append(self.exact(text))
            elif text[:1].isspace() or text[-1:].isspace() or any(w in text for w in _UNEVEN):
                out.append(self.direct(text))
            else:
                head, *rest = text.split(" ")
                out.append((head, rest, list(map(known.get, rest))))
        new = {c for x in out if type(x) is tuple and None in x[2] for c, got in zip(x[1], x[2]) if got is None}
        if new:
            if known.bytes > known.limit:
                known.clear()
            fresh = list(new)
            ids = np.array(self.core.encode_ordinary(" " + " ".join(fresh)), "<u4")
            ends = np.cumsum([len(c.encode()) + 1 for c in fresh])
            cuts = np.searchsorted(np.cumsum(self.sizes[ids]), ends) + 1
            raw, lo, found = ids.tobytes(), 0, {}
            for c, hi in zip(fresh, (cuts * 4).tolist()):
                found[c] = raw[lo:hi]
                lo = hi
            for c, raw in found.items():
                known.keep(c, raw)
        return [x if type(x) is bytes else self.heads[x[0]] + b"".join([found[c] if got is None else got for c, got in zip(x[1], x[2])] if None in x[2] else x[2]) for x in out]


def encoder_of(file: str) -> ByteBpe:
    return common.kept_by_worker(("byte-bpe", file), lambda: ByteBpe(file))


class Pool:
    """Items with demand vectors, and the choice of the next one by dot product."""

    def __init__(self, limits: list[float]):
        self.limits = np.array(limits, float)
        self.demand = np.zeros((0, len(limits)))
        self.items: list = []

    def set(self, items: list, demand: np.ndarray) -> None:
        self.items, self.demand, self.free = items, np.asarray(demand, float).reshape(len(items), len(self.limits)), np.ones(len(items), bool)

    def best(self, left: np.ndarray) -> int:
        fits = self.free & (self.demand <= left).all(1)
        if not fits.any():
            return -1
        value = (self.demand / self.limits) @ (left / self.limits)
        return int(np.argmax(np.where(fits, value, -1.0)))


def pack_vectors(demand: np.ndarray, limits: list[float]) -> np.ndarray:
    """Bin number of each item, uncut; an item that is over a limit by itself gets a bin of its own."""
    pool = Pool(limits)
    pool.set(list(range(len(demand))), demand)
    bins, b = np.full(len(demand), -1, np.int64), 0
    while pool.free.any():
        left, got = pool.limits.copy(), 0
        while (k := pool.best(left)) >= 0:
            pool.free[k] = False
            left -= pool.demand[k]
            bins[k], got = b, got + 1
        if not got:
            k = int(np.argmax(pool.free))
            pool.free[k], bins[k] = False, b
        b += 1
    return bins


def pack_examples(df: DataFrame, id_col: str, limits: dict[str, float], window: int = 4096) -> DataFrame:
    """(id, bin_id) for uncut examples whose demand columns are named in limits; null demands count as 0."""
    names, most = list(limits), list(limits.values())

    def run(batches):
        pid, bins = TaskContext.get().partitionId(), 0
        for batch in batches:
            for lo in range(0, batch.num_rows, window):
                part = batch.slice(lo, window)
                got = pack_vectors(np.stack([np.nan_to_num(np.array(part.column(n).to_pylist(), float)) for n in names], 1), most)
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array((pid << 33) + bins + got)], ["id", "bin_id"])
                bins += int(got.max()) + 1

    return df.select(F.col(id_col).cast("long").alias("id"), *[F.col(n).cast("double").alias(n) for n in names]).mapInArrow(run, "id long, bin_id long")


PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class Packer:
    """Pieces of documents in sequences of at most `size` ids."""

    def __init__(self, size: int, segments: int, loss: int, first: int, window: int):
        self.size, self.limits, self.next, self.window = size, [size, segments, loss], first, window
        self.rest: list[tuple] = []  # (doc_id, ids, start, doc_tokens)
        self.out: list[tuple] = []

    def add(self, doc_id, ids: np.ndarray) -> None:
        n = len(ids)
        full = n // self.size * self.size
        for at in range(0, full, self.size):
            self.emit([(doc_id, ids[at : at + self.size], at, n)])
        if full < n:
            self.rest.append((doc_id, ids[full:].copy(), full, n))
            if len(self.rest) >= self.window:
                self.pack(last=False)

    def emit(self, pieces: list[tuple]) -> None:
        offset = 0
        for doc_id, ids, start, n in pieces:
            self.out.append((doc_id, start, len(ids), zlib.crc32(ids), n, self.next, offset))
            offset += len(ids)
        self.next += 1

    @staticmethod
    def demand(item: tuple) -> tuple:
        _, ids, start, n = item
        return len(ids), 1, len(ids) - (start + len(ids) == n)  # the end id bears no loss

    def pack(self, last: bool) -> None:
        pool, items = Pool(self.limits), self.rest
        pool.set(items, np.array([self.demand(x) for x in items]))
        self.rest, total = [], sum(len(x[1]) for x in items)
        while total >= self.size or last and total:
            room = self.size if total >= self.size else 1 << (total.bit_length() - 1)
            left, got = np.minimum(pool.limits, [room, np.inf, np.inf]), []
            while left[0] > 0:
                k = pool.best(left)
                if k < 0:  # cut the largest item
                    if left[1] < 1 or left[2] < 1 or not pool.free.any():
                        break
                    k = int(np.argmax(np.where(pool.free, pool.demand[:, 0], -1)))
                    take = int(min(left[0], left[2], pool.demand[k, 0]))
                    doc_id, ids, start, n = items[k]
                    piece = (doc_id, ids[:take], start, n)
                    items[k] = (doc_id, ids[take:], start + take, n)
                    pool.demand[k] = self.demand(items[k])
                    pool.free[k] = len(items[k][1]) > 0
                else:
                    piece = items[k]
                    pool.free[k] = False
                left -= self.demand(piece)
                got.append(piece)
            total -= sum(len(p[1]) for p in got)
            self.emit(got)
        self.rest = [x for x, f in zip(items, pool.free) if f]

    def taken(self) -> list[tuple]:
        out, self.out = self.out, []
        return out


def pack_documents(docs: DataFrame, file: str, size: int = 1024, segments: int = 256, loss: int | None = None, end_id: int = 0, window: int = 768, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Tokenise whole texts, end each with end_id and pack their pieces; one row per piece."""
    names = [c.split()[0] for c in PIECE.split(", ")]
    end = np.array([end_id], "<u4").tobytes()

    def run(batches):
        encoder = encoder_of(file)
        packer = Packer(size, segments, loss or size, TaskContext.get().partitionId() << 33, window)

        def rows():
            got = packer.taken()
            return pa.RecordBatch.from_arrays([pa.array([r[k] for r in got], pa.int64()) for k in range(len(names))], names)

        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                for doc_id, ids in zip(part.column("i").to_pylist(), encoder.encode_batch(common.texts_of(part, "t"))):
                    packer.add(doc_id, np.frombuffer(ids + end, "<u4"))
                yield rows()
        packer.pack(last=True)
        yield rows()

    return docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")).mapInArrow(run, PIECE)
