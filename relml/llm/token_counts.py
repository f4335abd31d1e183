"""Token counts without token lists: Viterbi over a unigram vocabulary that carries only score and piece count.

The vocabulary is a public sentencepiece file: its pieces and their stored scores, read as unigram weights.  The exact
reference is the `tokenizers` Unigram model over the same pieces (byte fallback, space escaped as U+2581 with one put in
front).  Ties follow that library: at each end position the candidate that starts first wins, and a later one replaces
it only with a strictly greater score; an unknown character costs the least score minus 10.

Texts are cut where no piece can straddle (before a run of spaces, around line ends), so each distinct chunk is solved
once per worker: scores are whole numbers, hence sums are exact and the cut changes neither score nor tie.

Null and empty texts give 0 pieces and score 0.  Repeated rows give repeated results; other columns are ignored.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

UNKNOWN_PENALTY = 10.0
SPACE = "▁"


class CountingViterbi:
    """Score and number of pieces of the best segmentation."""

    def __init__(self, pieces: dict[str, float], byte_fallback: bool = True, unk: str = "<unk>", cache: int = common.LARGE_CACHE_BYTES):
        import ahocorasick

        self.auto = ahocorasick.Automaton()
        for piece, score in pieces.items():
            if piece and piece != unk:
                self.auto.add_word(piece, (len(piece), float(score)))
        self.auto.make_automaton()
        self.unk_score = min(pieces.values()) - UNKNOWN_PENALTY
        self.byte_fallback = byte_fallback
        inner = [p for p in pieces if SPACE in p.lstrip(SPACE)]
        breaks = [p for p in pieces if "\n" in p]
        exact = all(float(s).is_integer() for s in pieces.values())
        self.chunks = re.compile(f"\n|{SPACE}+[^{SPACE}\n]*|[^{SPACE}\n]+") if exact and not inner and not breaks else None
        self.cache = common.Known(limit=cache, size=lambda got: 100)

    def solve(self, text: str) -> tuple[float, int]:
        n = len(text)
        best, count, fused = [0.0] * (n + 1), [0] * (n + 1), [False] * (n + 1)
        at = 0  # positions below are final
        single = False
        none = float("-inf")

        def unknown(e: int, score: float, k: int, f: bool, one: bool) -> None:
            # the unknown edge starts last of all candidates that end at e, so it is tried last
            if not one:
                s = best[e - 1] + self.unk_score
                if s > score:
                    score = s
                    if self.byte_fallback:
                        k, f = count[e - 1] + len(text[e - 1].encode("utf-8", "surrogatepass")), True
                    else:
                        k, f = count[e - 1] + (not fused[e - 1]), True
            best[e], count[e], fused[e] = score, k, f

        score, k = none, 0
        for end, (size, weight) in self.auto.iter(text):
            e = end + 1
            while at + 1 < e:
                at += 1
                unknown(at, score, k, False, single)
                score, k, single = none, 0, False
            s = best[e - size] + weight
            if s > score:
                score, k = s, count[e - size] + 1
            if size == 1:
                single = True
        while at < n:
            at += 1
            unknown(at, score, k, False, single)
            score, k, single = none, 0, False
        return best[n], count[n]

    def count(self, text: str) -> tuple[float, int]:
        if not text:
            return 0.0, 0
        text = SPACE + text.replace(" ", SPACE)
        if self.chunks is None:
            return self.solve(text)
        cache, score, pieces = self.cache, 0.0, 0
        for chunk in self.chunks.findall(text):
            got = cache.get(chunk)
            if got is None:
                got = self.solve(chunk)
                if len(chunk) < 64:
                    cache.keep(chunk, got)
            score += got[0]
            pieces += got[1]
        return score, pieces


def vocabulary(model_file: str) -> dict[str, float]:
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
    return {sp.id_to_piece(i): sp.get_score(i) for i in range(sp.vocab_size()) if not sp.is_control(i) and not sp.is_byte(i)}


def viterbi_of(model_file: str) -> CountingViterbi:
    """One per worker process: its chunk cache lives on from task to task."""
    return common.kept_by_worker(("viterbi", model_file), lambda: CountingViterbi(vocabulary(model_file)))


def token_counts(docs: DataFrame, model_file: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_pieces, score) for each row."""

    def make():
        solver = viterbi_of(model_file)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = [solver.count(x) for x in common.texts_of(batch, "t")]
            return pa.RecordBatch.from_arrays([batch.column("i"), pa.array([k for _, k in got], pa.int64()), pa.array([s for s, _ in got], pa.float64())], ["doc_id", "n_pieces", "score"])

        return step

    df = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    return common.map_batches(df, make, "doc_id long, n_pieces long, score double")
