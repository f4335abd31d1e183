"""Exact BPE encoding and decoding with a minimal acyclic transducer for frequent words.

Frequent words, counted over the whole corpus, are compiled with their id lists into an automaton whose equal suffixes
are shared (sorted insertion, states merged by signature), so it is the smallest acyclic one.  A word's place in the
sorted list is the sum of counts along its path and indexes one flat array of ids.  The automaton is three numpy arrays in
files of the shared folder, memory-mapped by each worker.  Words that are not in it are merged exactly by rank.

Null text counts as empty; empty text gives 0 ids and the digest of the empty string.  Repeated rows repeat.
"""

from __future__ import annotations

import hashlib
import io
import json
import re
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

_SPACE = re.compile("[ \t\n\r]+")
_ODD = re.compile("[^\t\n\r -~¡-ɏ‐-‧]|[ª­²³µ¹º¼-¾İĲĳŉſ]")


def byte_alphabet() -> dict[int, str]:
    """The printable stand-in of each byte that byte-level vocabularies use."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(hidden)}


class Transducer:
    """Minimal acyclic automaton over UTF-8 bytes: word -> its rank among the sorted words -> ids."""

    def __init__(self, first: np.ndarray, labels: np.ndarray, targets: np.ndarray, before: np.ndarray, final: np.ndarray, starts: np.ndarray, ids: np.ndarray):
        self.arrays = (first, labels, targets, before, final, starts, ids)
        self.labels = labels.tobytes()  # small; the rest is read where it is mapped
        self.first, self.targets, self.before, self.final, self.starts = (memoryview(np.ascontiguousarray(a)) for a in (first, targets, before, final.view(np.uint8), starts))

    @classmethod
    def compile(cls, entries: dict[str, list[int]]) -> "Transducer":
        words = sorted((w.encode(), v) for w, v in entries.items())
        register: dict[tuple, int] = {}
        done: list[tuple[bool, tuple, int]] = []  # final, ((byte, state), ...), words below

        def close(node: list) -> int:
            key = (node[0], tuple(node[1]))
            if key not in register:
                register[key] = len(done)
                done.append((node[0], key[1], node[0] + sum(done[t][2] for _, t in node[1])))
            return register[key]

        path: list[list] = [[False, []]]  # open nodes on the path of the last word
        last = b""
        for word, _ in words:
            common_len = next((k for k, (a, b) in enumerate(zip(word, last)) if a != b), min(len(word), len(last)))
            while len(path) > common_len + 1:
                node = path.pop()
                path[-1][1].append((last[len(path) - 1], close(node)))
            for _ in word[common_len:]:
                path.append([False, []])
            path[-1][0] = True
            last = word
        while len(path) > 1:
            node = path.pop()
            path[-1][1].append((last[len(path) - 1], close(node)))
        root = close(path[0])
        order = [root, *[s for s in range(len(done)) if s != root]]
        new = {s: k for k, s in enumerate(order)}
        first, labels, targets, before = [0], [], [], []
        for s in order:
            seen = int(done[s][0])
            for b, t in done[s][1]:
                labels.append(b)
                targets.append(new[t])
                before.append(seen)
                seen += done[t][2]
            first.append(len(labels))
        starts = np.cumsum([0, *(len(v) for _, v in words)])
        return cls(np.array(first, np.int32), np.array(labels, np.uint8), np.array(targets, np.int32), np.array(before, np.int32), np.array([done[s][0] for s in order], bool), starts.astype(np.int64), np.array([i for _, v in words for i in v], np.int32))

    @property
    def states(self) -> int:
        return len(self.arrays[4])

    def find(self, word: str) -> list[int] | None:
        first, targets, before, find = self.first, self.targets, self.before, self.labels.find
        state = rank = 0
        for b in word.encode():
            k = find(b, first[state], first[state + 1])
            if k < 0:
                return None
            rank += before[k]
            state = targets[k]
        return self.arrays[6][self.starts[rank] : self.starts[rank + 1]].tolist() if self.final[state] else None

    def save(self, folder: str) -> None:
        from pyarrow import fs

        where, path = fs.FileSystem.from_uri(folder)
        where.create_dir(path)
        for k, a in enumerate(self.arrays):
            buf = io.BytesIO()
            np.save(buf, a)
            with where.open_output_stream(f"{path}/{k}.npy") as out:
                out.write(buf.getvalue())

    @classmethod
    def open(cls, folder: str) -> "Transducer":
        """Memory-mapped where the shared folder is a mounted one, else read once per worker."""
        from pyarrow import fs

        where, path = fs.FileSystem.from_uri(folder)
        if isinstance(where, fs.LocalFileSystem):
            return cls(*(np.load(f"{path}/{k}.npy", mmap_mode="r") for k in range(7)))
        return cls(*(np.load(io.BytesIO(where.open_input_file(f"{path}/{k}.npy").read())) for k in range(7)))


class WordBpe:
    """BPE with a word-end suffix over a tokenizer file: words by the file's pattern, merges by rank."""

    WORDS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\s\w]|_)+")

    def __init__(self, file: str):
        self.spec = json.load(open(file, encoding="utf-8"))
        model = self.spec["model"]
        self.vocab = model["vocab"]
        self.tokens = {i: t for t, i in self.vocab.items()} | {a["id"]: a["content"] for a in self.spec["added_tokens"]}
        self.special = [a["content"] for a in self.spec["added_tokens"]]
        self.spaced = [s for s in self.special if _SPACE.search(s)]  # such a token may straddle chunks
        merges = (m.split(" ") if isinstance(m, str) else m for m in model["merges"])
        self.ranks = {(a, b): k for k, (a, b) in enumerate(merges)}
        self.end = model["end_of_word_suffix"] or ""
        self.alphabet = byte_alphabet()
        self.file = file
        self._exact = None

    def exact(self):
        """The library itself, for texts with characters whose class or case is not the same in all Unicode tables."""
        if self._exact is None:
            from tokenizers import Tokenizer

            self._exact = Tokenizer.from_file(self.file)
            self._exact.no_truncation()
            self._exact.no_padding()
        return self._exact

    def words(self, text: str) -> list[str] | None:
        """The words of a text; None if only the library can tell."""
        return None if self.odd(text) else self.WORDS.findall(text.lower())

    def odd(self, text: str) -> bool:
        return bool(_ODD.search(text)) or any(s in text for s in self.special)

    def merge(self, word: str) -> list[int]:
        parts = [self.alphabet[b] for b in word.encode()]
        parts[-1] += self.end
        rank, far = self.ranks.get, 1 << 60
        order = [rank(pair, far) for pair in zip(parts, parts[1:])]
        while order and (low := min(order)) < far:
            k = order.index(low)  # leftmost of the lowest rank, one at a time
            parts[k : k + 2] = [parts[k] + parts[k + 1]]
            del order[k]
            if k:
                order[k - 1] = rank((parts[k - 1], parts[k]), far)
            if k < len(order):
                order[k] = rank((parts[k], parts[k + 1]), far)
        return [self.vocab[p] for p in parts if p in self.vocab]


class Codec:
    """Encoder and decoder of one worker: the mapped automaton first, exact merging next, results kept by word."""

    def __init__(self, file: str, folder: str | None, cache: int = common.LARGE_CACHE_BYTES):
        self.bpe = WordBpe(file)
        self.lexicon = Transducer.open(folder) if folder else None
        size = lambda got: 250 + len(got[1]) + 2 * len(got[2])
        self.known, self.odd = common.Known(self.learn, cache, size), common.Known(self.strange, cache // 16, size)

    def ids(self, word: str) -> list[int]:
        got = self.lexicon.find(word) if self.lexicon else None
        return self.bpe.merge(word) if got is None else got

    def learn(self, chunk: str) -> tuple[int, str, str]:
        """Of a chunk between white space: words don't straddle it."""
        ids = [i for w in self.bpe.WORDS.findall(chunk) for i in self.ids(w)]
        return len(ids), " ".join(map(str, ids)), self.decode(ids)

    def decode(self, ids: list[int]) -> str:
        """The file has no decoder, so its tokens are joined by spaces."""
        return " ".join(self.bpe.tokens[i] for i in ids)

    def encode(self, text: str) -> list[int]:
        return [int(i) for g in self.chunks(text) if g[0] for i in g[1].split(" ")]

    def strange(self, chunk: str) -> tuple[int, str, str]:
        """A chunk whose characters' class or case is not the same in all Unicode tables, by the library."""
        ids = self.bpe.exact().encode(chunk, add_special_tokens=False).ids
        return len(ids), " ".join(map(str, ids)), self.decode(ids)

    def chunks(self, text: str) -> list[tuple[int, str, str]]:
        """Results of the chunks between white space, in which no word straddles.  Only chunks with odd characters go to the
        library, not the text around them."""
        plain = text if text.isascii() else unicodedata.normalize("NFC", text)
        if not self.bpe.odd(plain):
            return list(map(self.known.__getitem__, plain.lower().split()))
        if self.bpe.spaced and any(s in text for s in self.bpe.spaced):
            return [self.strange(text)]
        out = []
        for chunk in _SPACE.split(text):
            plain = chunk if chunk.isascii() else unicodedata.normalize("NFC", chunk)
            if self.bpe.odd(chunk) or self.bpe.odd(plain):
                out.append(self.odd[chunk])
            elif plain:
                out.append(self.known[plain.lower()])
        return out

    def digests(self, text: str) -> tuple[int, str, str]:
        sha, got = hashlib.sha256, [g for g in self.chunks(text) if g[0]]
        return sum([g[0] for g in got]), sha(" ".join([g[1] for g in got]).encode()).hexdigest(), sha(" ".join([g[2] for g in got]).encode()).hexdigest()


def frequent_words(docs: DataFrame, text_col: str = "text", size: int = 20_000) -> list[str]:
    """The most frequent words of the whole corpus, ties by word; size is the feature of the lexicon and only steers
    speed.  Counting is native, pre-aggregated before its shuffle, over words cut at white space and non-letters.  The
    count from which words are sent to the driver comes from a histogram of the counts in eighths of powers of two, so that
    what it gets does not grow with the corpus or its partitions."""
    words = docs.select(F.explode(F.split(F.lower(F.col(text_col)), r"[^\p{L}]+")).alias("w")).where("w <> ''")
    seen = common.settle(words.groupBy("w").count().where("count > 1"), "words")
    level = F.floor(F.log2(F.col("count").cast("double")) * 8).cast("int")
    least, held = 0, 0
    for r in sorted(seen.groupBy(level.alias("level")).count().collect(), key=lambda r: -r.level):  # some hundred at most
        least, held = r.level, held + r["count"]
        if held >= size:
            break
    rows = seen.where(level > least).collect()
    more = size - len(rows)
    if more > 0:
        rows += seen.where(level == least).orderBy(F.desc("count"), "w").limit(more).collect()
    common.discard(seen)
    return [r.w for r in sorted(rows, key=lambda r: (-r["count"], r.w))]


def codec_of(file: str, folder: str | None) -> Codec:
    return common.kept_by_worker(("word-bpe", file, folder), lambda: Codec(file, folder))


def build_lexicon(spark: SparkSession, words: list[str], file: str) -> str:
    bpe = WordBpe(file)
    entries = {w: bpe.merge(w) for w in words if bpe.words(w) == [w]}
    folder = common.new_path(spark, "lexicon")
    folder = folder if ":" in folder.split("/")[0] else f"file://{folder}"
    Transducer.compile(entries).save(folder)
    return folder


def encode_documents(docs: DataFrame, file: str, folder: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids, decoded) with the real outputs."""

    def make():
        codec = codec_of(file, folder)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            ids = [codec.encode(x) for x in common.texts_of(batch, "t")]
            return pa.RecordBatch.from_arrays([batch.column("i"), pa.array(ids, pa.list_(pa.int32())), pa.array([codec.decode(x) for x in ids], pa.string())], ["doc_id", "ids", "decoded"])

        return step

    return common.map_batches(docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")), make, "doc_id long, ids array<int>, decoded string")


def encode_digests(docs: DataFrame, file: str, folder: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of the same outputs, never held as lists."""

    def make():
        codec = codec_of(file, folder)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = [codec.digests(x) for x in common.texts_of(batch, "t")]
            return pa.RecordBatch.from_arrays([batch.column("i"), pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.string()), pa.array([g[2] for g in got], pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

        return step

    return common.map_batches(docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")), make, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
