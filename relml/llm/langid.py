"""Language identification: a bidirectional gated recurrent network over bytes, trained in numpy.

The network reads the UTF-8 bytes of a whole lower-cased text, letters, digits and white space alike, forwards and
backwards in windows of 64 bytes, and labels every byte position with language probabilities.  A document's value for a
language is the mean over its positions of the log probability, brought back to probabilities.  Windows bound the reach of
the states and the memory of a worker, which keeps nothing from text to text; every byte lies in one window.  Gates and
states use x / (1 + |x|), which costs a fifth of the hyperbolic tangent.

Training: backpropagation through time on windows drawn from the whole texts of a bounded sample of labelled documents, as
many windows from each language.  Texts that are null or have no letter give `und` with score 0.  Ties go to the first
language by name.  Repeated rows give equal results.  Without training rows every text is `und`.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

_LETTER = re.compile(r"[^\W\d_]")
WINDOW = 64
PAD = 256
LOT = 2048  # windows that are read together
UNKNOWN = "und"
PARTS = 256  # of a language's rows when its sample is drawn


def squash(x: np.ndarray) -> np.ndarray:
    """x / (1 + |x|), in place."""
    d = np.abs(x)
    d += 1
    x /= d
    return x


class ByteGru:
    """Two GRUs over bytes and one softmax over both states at each position.  Arrays lie as (values, windows)."""

    def __init__(self, languages: list[str], hidden: int = 12, seed: int = 7):
        rng, k, h = np.random.default_rng(seed), len(languages), hidden
        self.languages, self.hidden = languages, hidden
        self.p: dict[str, np.ndarray] = {"o": np.zeros((k, 1), np.float32)}
        for d in "fb":
            # W: what a byte adds to reset gate, update gate and candidate
            self.p |= {f"W{d}": rng.normal(0, 0.5, (3 * h, PAD + 1)).astype(np.float32), f"U{d}": rng.normal(0, h**-0.5, (3 * h, h)).astype(np.float32), f"O{d}": rng.normal(0, 0.3, (k, h)).astype(np.float32)}

    def sweep(self, codes: np.ndarray, d: str, kept: list | None = None) -> np.ndarray:
        """States (time, hidden, windows) in reading order of direction d; kept takes what the way back needs."""
        h, W, U = self.hidden, self.p[f"W{d}"], self.p[f"U{d}"]
        steps, n = codes.shape
        out, state, pad = np.empty((steps, h, n), W.dtype), np.zeros((h, n), W.dtype), codes == PAD
        padded = pad.any(1)
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            a, u = np.take(W, codes[t], axis=1), U @ state
            gates = a[: 2 * h]
            gates += u[: 2 * h]
            squash(gates)
            gates *= 0.5
            gates += 0.5
            ug = u[2 * h :] if kept is None else u[2 * h :].copy()
            new = u[2 * h :]
            new *= gates[:h]
            new += a[2 * h :]
            squash(new)
            if kept is not None:
                kept.append((t, state, gates[:h], gates[h:], new, ug))
            np.subtract(state, new, out=out[t])
            out[t] *= gates[h:]
            out[t] += new
            if padded[t]:
                out[t][:, pad[t]] = 0  # a text's end is where the way back starts
            state = out[t]
        return out

    def log_probabilities(self, f: np.ndarray, b: np.ndarray) -> np.ndarray:
        """(time, languages, windows)."""
        logits = self.p["Of"] @ f + self.p["Ob"] @ b + self.p["o"]
        logits -= logits.max(1, keepdims=True)
        logits -= np.log(np.exp(logits).sum(1, keepdims=True))
        return logits

    def label(self, codes: np.ndarray) -> np.ndarray:
        return self.log_probabilities(self.sweep(codes, "f"), self.sweep(codes, "b"))

    def back(self, dout: np.ndarray, codes: np.ndarray, kept: list, d: str, grad: dict) -> None:
        h, U = self.hidden, self.p[f"U{d}"]
        dstate = np.zeros(dout.shape[1:], dout.dtype)
        for t, state, r, z, g, ug in reversed(kept):
            dnew = (dstate + dout[t]) * (codes[t] < PAD)
            dg = dnew * (1 - z) * (1 - np.abs(g)) ** 2
            dz = dnew * (state - g) * slope(z)
            dr = dg * ug * slope(r)
            np.add.at(grad[f"W{d}"].T, codes[t], np.concatenate([dr, dz, dg]).T)
            du = np.concatenate([dr, dz, dg * r])
            grad[f"U{d}"] += du @ state.T
            dstate = dnew * z + U.T @ du

    def gradient(self, codes: np.ndarray, target: np.ndarray) -> tuple[float, dict]:
        """codes (time, windows); target: each window's language.  The loss is a mean over labelled positions."""
        kf, kb = [], []
        f, b = self.sweep(codes, "f", kf), self.sweep(codes, "b", kb)
        logp = self.log_probabilities(f, b)
        on = (codes < PAD)[:, None] / max(1, int((codes < PAD).sum()))
        hit = (np.arange(len(self.languages))[:, None] == target)[None]
        loss = float(-(logp * hit * on).sum())
        dlogit = ((np.exp(logp) - hit) * on).astype(logp.dtype)
        grad = {k: np.zeros_like(v) for k, v in self.p.items()}
        grad["o"] = dlogit.sum((0, 2))[:, None]
        for d, states, kept in (("f", f, kf), ("b", b, kb)):
            grad[f"O{d}"] = np.einsum("tkn,thn->kh", dlogit, states)
            self.back(self.p[f"O{d}"].T @ dlogit, codes, kept, d, grad)
        return loss, grad

    def train(self, windows: list[np.ndarray], steps: int = 240, batch: int = 160, rate: float = 0.02, seed: int = 7) -> "ByteGru":
        """windows: for each language its windows (time, windows)."""
        rng, m, v = np.random.default_rng(seed), {k: 0 for k in self.p}, {k: 0 for k in self.p}
        target = np.repeat(np.arange(len(windows)), -(-batch // max(1, len(windows))))
        for t in range(1, steps + 1):
            codes = np.concatenate([w[:, rng.integers(0, w.shape[1], -(-batch // len(windows)))] for w in windows], 1)
            _, grad = self.gradient(codes, target)
            norm = np.sqrt(sum(float((g * g).sum()) for g in grad.values()))
            for key, g in grad.items():
                g = g * min(1, 1 / max(norm, 1e-9))
                m[key], v[key] = 0.9 * m[key] + 0.1 * g, 0.99 * v[key] + 0.01 * g * g
                self.p[key] = (self.p[key] - rate * (1 - t / (steps + 1)) * (m[key] / (1 - 0.9**t)) / (np.sqrt(v[key] / (1 - 0.99**t)) + 1e-8)).astype(np.float32)
        return self

    def documents(self, texts: list[str]) -> list[tuple[str, float]]:
        """(language, score) of each text."""
        out: list = [(UNKNOWN, 0.0)] * len(texts)
        at = [k for k, t in enumerate(texts) if _LETTER.search(t)] if self.languages else []
        if not at:
            return out
        raw = [texts[k].lower().encode() for k in at]
        total, sizes = np.zeros((len(at), len(self.languages))), np.array([len(x) for x in raw])
        for codes, owner in lots(raw):
            logp = self.label(codes)
            logp *= (codes < PAD)[:, None]
            np.add.at(total, owner, np.round(logp.sum(0, dtype=np.float64).T, 3))
        mean = total / sizes[:, None]
        p = np.exp(mean - mean.max(1, keepdims=True))
        for k, row in zip(at, p):
            best = int(np.argmax(row))
            out[k] = self.languages[best], float(row[best] / row.sum())
        return out


def slope(gate: np.ndarray) -> np.ndarray:
    """Derivative of 0.5 + 0.5 x / (1 + |x|) by its value."""
    return 0.5 * (1 - np.abs(2 * gate - 1)) ** 2


def windows_of(raw: bytes) -> np.ndarray:
    """Codes (time, windows) of one text; the last window is filled with PAD."""
    codes = np.full((-(-len(raw) // WINDOW), WINDOW), PAD, np.int16)
    codes.ravel()[: len(raw)] = np.frombuffer(raw, np.uint8)
    return codes.T


def lots(raw: list[bytes]):
    """(codes, number of the text of each window), at most LOT windows at a time."""
    held, owner, n = [], [], 0
    for k, x in enumerate(raw):
        w = windows_of(x)
        for lo in range(0, w.shape[1], LOT):
            part = w[:, lo : lo + LOT]
            if n + part.shape[1] > LOT:
                yield np.concatenate(held, 1), np.repeat(*zip(*owner))
                held, owner, n = [], [], 0
            held.append(part)
            owner.append((k, part.shape[1]))
            n += part.shape[1]
    if held:
        yield np.concatenate(held, 1), np.repeat(*zip(*owner))


def train(docs: DataFrame, usable: Column, per_language: int = 300, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> ByteGru:
    """Fit on the whole texts of at most per_language documents of each language: those whose hashed id is least among all
    usable rows.  The driver holds those texts."""
    rows = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull() & usable).select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"), F.col(lang_col).alias("l"))
    order, few = [F.xxhash64("i"), "i"], rows.select("i", "l").withColumn("part", F.pmod(F.crc32(F.col("i").cast("string").cast("binary")), F.lit(PARTS)))
    for by in (["l", "part"], ["l"]):  # the least of each part first, so that no task gets a language from all partitions
        few = few.withColumn("k", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("k") <= per_language).drop("k")
    few = few.select("i", "l").distinct()
    texts: dict[str, list[str]] = {}
    for r in rows.join(F.broadcast(few), ["i", "l"]).collect():
        if _LETTER.search(r.t):
            texts.setdefault(r.l, []).append(r.t)
    languages = sorted(texts)
    if not languages:
        return ByteGru([])
    return ByteGru(languages).train([np.concatenate([windows_of(t.lower().encode()) for t in sorted(texts[l])], 1) for l in languages])


def _labeller(docs: DataFrame, model: ByteGru):
    held = docs.sparkSession.sparkContext.broadcast(model)  # some thousand numbers
    return lambda texts: held.value.documents(texts)


def predict(docs: DataFrame, model: ByteGru, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) of each row."""
    values = _labeller(docs, model)

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = values(common.texts_of(batch, "t"))
            return pa.RecordBatch.from_arrays([batch.column("i"), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())], ["doc_id", "lang_pred", "score"])

        return step

    return common.map_batches(docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")), make, "doc_id long, lang_pred string, score double")


def keep_known(docs: DataFrame, model: ByteGru, least: float = 0.3, text_col: str = "text") -> DataFrame:
    """The rows of docs, all columns, with a language whose score is at least `least`: texts without letters go, and
    those in which no language stands out."""
    values = _labeller(docs, model)

    def make():
        return lambda batch: common.keep(batch, [l != UNKNOWN and s >= least for l, s in values(common.texts_of(batch, text_col))])

    return common.map_batches(docs, make, docs.schema)
