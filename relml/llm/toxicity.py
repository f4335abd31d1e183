"""Toxicity classifier with a counterfactual penalty.

Features of a text: its set of lower-case words, and the set of their first 4, 5 and 6 letters.  Document frequencies of a
bounded labelled sample choose the features that tell; a logistic model over their presence is fitted by gradient descent
on: log loss + l2 + penalty * squared change of the logit between a sentence and its counterfactual, the same sentence
with each identity term swapped for another of its group.  Every identity term is a feature, so that the penalty and not
chance rules its weight; sentences made of one term each keep unseen terms alike too.

Scores: whole texts, by look-up of features; label, language, source and id are no inputs.  Null and empty texts get the
score of no features.  Repeated rows get equal scores.  Without labelled rows of both kinds the score is the share of 1s
(0 without any).
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

#: Terms within one group are swapped for each other.
IDENTITY_GROUPS = (
    ("women", "men", "girls", "boys", "mothers", "fathers"),
    ("woman", "man", "girl", "boy", "mother", "father"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist", "catholic", "protestant"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists", "catholics", "protestants"),
    ("black", "white", "asian", "latino", "african", "european", "arab", "indigenous"),
    ("gay", "straight", "lesbian", "bisexual", "transgender", "queer"),
    ("immigrants", "natives", "refugees", "citizens", "foreigners"),
    ("disabled", "blind", "deaf", "elderly", "young"),
    ("femmes", "hommes", "musulmans", "juifs"),
    ("frauen", "männer", "muslime", "juden", "ausländer"),
    ("mujeres", "hombres", "musulmanes", "judíos", "inmigrantes"),
)
_WORD = re.compile(r"[^\W\d_]+")


def features(text: str) -> set[str]:
    words = set(_WORD.findall(text.lower()))
    return words | {f"{n}^{w[:n]}" for w in words for n in (4, 5, 6) if len(w) > n}


def counterfactual(text: str, shift: int = 1) -> str:
    """Each identity term swapped for the term `shift` places on in its group."""
    swap = {w: g[(k + shift) % len(g)] for g in IDENTITY_GROUPS for k, w in enumerate(g)}
    return _WORD.sub(lambda m: swap.get(m[0].lower(), m[0]), text)


@dataclass
class ToxicityModel:
    weights: dict[str, float] = field(default_factory=dict)
    bias: float = 0.0

    def __post_init__(self):
        self.words = {k: v for k, v in self.weights.items() if "^" not in k}
        self.stems = [(n, {k[2:]: v for k, v in self.weights.items() if k.startswith(f"{n}^")}) for n in (4, 5, 6)]

    def logit(self, text: str) -> float:
        words = set(_WORD.findall(text.lower()))
        total = self.bias + sum(self.words[w] for w in sorted(words & self.words.keys()))
        for n, table in self.stems:
            if table:
                total += sum(table[s] for s in sorted({w[:n] for w in words if len(w) > n} & table.keys()))
        return total

    def score(self, text: str | None) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.logit(text or ""), -30, 30))))


def fit(texts: list[str], labels: list[int], penalty: float = 10.0, l2: float = 3e-4, least: int = 5, most: int = 3000, steps: int = 400, rate: float = 0.5) -> ToxicityModel:
    y = np.array(labels, float)
    if not len(y) or y.min() == y.max():
        return ToxicityModel({}, float(np.log((y.sum() + 1e-9) / (len(y) - y.sum() + 1e-9))) if len(y) else -30.0)
    counts = Counter(), Counter()
    for t, label in zip(texts, labels):
        counts[label].update(features(t))
    pos, neg = y.sum(), len(y) - y.sum()
    names = [f for f in counts[1] if counts[1][f] + counts[0].get(f, 0) >= least]
    names += [f for f, n in counts[0].items() if n >= least and f not in counts[1]]
    a, b = (np.array([counts[k].get(f, 0) for f in names], float) for k in (1, 0))
    del counts
    p, q, both = a / pos, b / neg, (a + b) / len(y)
    z = np.abs(p - q) / np.sqrt(np.maximum(both * (1 - both) * (1 / pos + 1 / neg), 1e-12))
    identity = sorted({w for g in IDENTITY_GROUPS for w in g})
    chosen = [names[k] for k in sorted(np.flatnonzero(z > 4), key=lambda k: (-z[k], names[k]))[:most]]
    chosen = list(dict.fromkeys([*chosen, *identity]))
    index = {f: k for k, f in enumerate(chosen)}
    sets = [features(t) & index.keys() for t in texts]  # the features are worked out again, not held

    def sparse(rows: list[set[str]]) -> tuple[np.ndarray, np.ndarray]:
        at = [(i, index[f]) for i, r in enumerate(rows) for f in r if f in index]
        return np.array([i for i, _ in at], np.int64), np.array([k for _, k in at], np.int64)

    r, c = sparse(sets)
    named = set(identity)
    pairs = [(s, features(counterfactual(t)) & index.keys()) for s, t in zip(sets, texts) if s & named]
    pairs += [({g[k]}, {g[(k + 1) % len(g)]}) for g in IDENTITY_GROUPS for k in range(len(g))]
    pairs += [({g[0]}, set()) for g in IDENTITY_GROUPS]  # a neutral mention against none
    (ra, ca), (rb, cb) = sparse([x for x, _ in pairs]), sparse([x for _, x in pairs])
    w, bias, n, m = np.zeros(len(chosen)), 0.0, len(y), len(pairs)
    mw, vw = np.zeros(len(w) + 1), np.zeros(len(w) + 1)
    weight = np.where(y == 1, 0.5 / pos, 0.5 / neg) * 0.5 + 0.5 / n  # rare label counts more, but not as much as the other
    for t in range(1, steps + 1):
        logit = np.bincount(r, w[c], n) + bias
        err = (1 / (1 + np.exp(-np.clip(logit, -30, 30))) - y) * weight
        diff = np.bincount(ra, w[ca], m) - np.bincount(rb, w[cb], m)
        g = np.bincount(c, err[r], len(w)) + l2 * w
        g += 2 * penalty / m * (np.bincount(ca, diff[ra], len(w)) - np.bincount(cb, diff[rb], len(w)))
        g = np.append(g, err.sum())
        mw, vw = 0.9 * mw + 0.1 * g, 0.99 * vw + 0.01 * g * g
        step = rate * (0.3 if t > steps // 2 else 1) * (mw / (1 - 0.9**t)) / (np.sqrt(vw / (1 - 0.99**t)) + 1e-8)
        w, bias = w - 0.2 * step[:-1], bias - 0.2 * step[-1]
    return ToxicityModel({f: float(v) for f, v in zip(chosen, w) if abs(v) > 1e-4}, float(bias))


def train(docs: DataFrame, labels: DataFrame, usable: Column, sample: int = 4_000, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> ToxicityModel:
    """Fit on the whole texts of at most `sample` labelled rows, those whose hashed id is least.  The driver holds them."""
    marked = labels.where(F.col(label_col).isin(0, 1)).select(F.col(id_col).cast("long").alias("i"), F.col(label_col).cast("int").alias("y"))
    marked = marked.where("i is not null").groupBy("i").agg(F.max("y").alias("y"))
    chosen = marked.where(usable(F.col("i")) if callable(usable) else usable).orderBy(F.xxhash64("i"), "i").limit(sample)
    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.coalesce(F.col(text_col), F.lit("")).alias("t")).join(F.broadcast(chosen), "i").collect()
    rows.sort(key=lambda x: (x.i, x.t))
    return fit([x.t for x in rows], [x.y for x in rows])


def score_documents(docs: DataFrame, model: ToxicityModel, threshold: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score, predicted) of each row."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # bounded by `most` features

    def make():
        model = held.value

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = [model.score(t) for t in common.texts_of(batch, "t")]
            return pa.RecordBatch.from_arrays([batch.column("i"), pa.array(got, pa.float64()), pa.array([int(s >= threshold) for s in got], pa.int32())], ["doc_id", "score", "predicted"])

        return step

    return common.map_batches(docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")), make, "doc_id long, score double, predicted int")


def keep_clean(docs: DataFrame, model: ToxicityModel, threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """The rows of docs, all columns, whose score is below the threshold."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        model = held.value
        return lambda batch: common.keep(batch, [model.score(t) < threshold for t in common.texts_of(batch, text_col)])

    return common.map_batches(docs, make, docs.schema)
