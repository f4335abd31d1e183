"""Removal of repeated line runs: suffixes of line-id sequences, grouped by distributed prefix doubling.

A text is a sequence of lines; a line ends at a line end, after a sentence end, or before a word that starts with a capital,
so a passage pasted into running text still falls into whole lines.  A line's id is its 64-bit hash.  The suffix of a
position is named by a hash of its first lines.  As a name is a hash of content and no rank, the rounds that double it up to
the least run with `least_words` words (level 0) need no exchange; the grouping of names is distributed.  Positions whose name
is unique leave; the rest come together by document once, and each round beyond joins two runs of the level below, end to
end, within a task.  The names of all these rounds are grouped at once: a name seen more than once has such halves, so no
interval is lost.  The intervals are those of suffixes with a common prefix, and the first position of one is its source.
Which lines go is settled at level 0: runs with an earlier source are joined into segments, and a segment's last run grows line
by line while the longer prefix still has an earlier place, so maximal repeated runs are cut whole.  Rounds beyond (`rounds`,
all if None) tell how deep a document's runs are.  Later copies go, the first in order of (doc_id, line) stays.

Between stages a document's lines are bytes of whole numbers, and a run is one long of document, first line and end where the
ids and lines of the corpus fit into 63 bits together, else a pair of longs; both have the order of (doc_id, line).

Documents that are wholly equal, and have enough words, go as one run, and their positions take no part in the doubling.

Null text stays null and has no lines.  Texts with no repeated run stay as they are, byte for byte; of others the lines go
and the rest stays with its separators, less white space at the end.  Rows that share an id are one document: each gets
the deletions of all.  Rows without an id are left alone.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

LEAST_WORDS = 40
_ROWS = 1024  # documents that a worker takes at a time
_CAPITAL = "A-ZÀ-ÖØ-ÞĀĂĄĆČĎĐĘĚŁŃŇŒŘŚŠŤŮŹŻŽΑ-ΩА-Я"
#: a run of white space that holds a line end, follows a sentence end or precedes a capital
_CUT = re.compile(rf"(\s(?:(?<=[.!?].)\s*|(?<=\n)\s*|[^\S\n]*\n\s*|\s*(?=[{_CAPITAL}])))", re.S)
_BASE = 0x9E3779B97F4A7C15  # odd
_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}


def lines_of(text: str) -> list[str]:
    return [x for x in _CUT.split(text)[::2] if x]


def starts_of(parts: list[str]) -> np.ndarray:
    """Character at which each line starts, from a split text with its separators."""
    sizes = np.fromiter(map(len, parts), np.int32, len(parts))
    at = np.cumsum(sizes) - sizes
    return at[::2][sizes[::2] > 0]


def powers(base: int, n: int) -> np.ndarray:
    """base ** 0 to base ** n, modulo 2 ** 64."""
    held = _powers.get(base)
    if held is None or len(held) <= n:
        held = np.full(2 * n + 1024, base, np.uint64)
        held[0] = 1
        held = _powers[base] = np.multiply.accumulate(held)
    return held[: n + 1]


def mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(29))


def seeds(units: np.ndarray, words: np.ndarray, stop: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(name, position, end) of the least run with `least` words from each position that has one before its document
    stops; the documents of a batch lie end to end.

    Rounds of prefix doubling: the name of 2^(k+1) lines is made of the names of its two halves, and that of a run of any
    length of the two runs of 2^k lines that cover it from both ends."""
    n = len(units)
    total = np.append(0, np.cumsum(words))
    end = np.searchsorted(total, total[:-1] + least)
    pos = np.flatnonzero(end <= stop)
    end = end[pos]
    size = end - pos
    name, out, step = mixed(units.astype(np.uint64)), np.zeros(len(pos), np.uint64), 1
    with np.errstate(over="ignore"):
        while len(pos):
            at = np.flatnonzero((size >= step) & (size < 2 * step))
            out[at] = mixed(paired(name[pos[at]], name[end[at] - step]) + size[at].astype(np.uint64))
            if int(size.max()) < 2 * step:
                break
            name[: n - step] = mixed(paired(name[: n - step], name[step:]))  # beyond a document's end it is not asked for
            step *= 2
    return out, pos, end


def paired(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return a * np.uint64(_BASE) + (b ^ (b >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)


def _line_table(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    def make():
        from xxhash import xxh64_intdigest

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            flat, words, starts, offsets, whole, length, total = [], [], [], [0], [], [], []
            for text in common.texts_of(batch, "t"):
                parts = _CUT.split(text)
                lines = [x for x in parts[::2] if x]
                ids = list(map(xxh64_intdigest, lines))
                counts = [x.count(" ") + 1 for x in lines]
                flat += ids
                words += counts
                starts.append(starts_of(parts))
                offsets.append(len(flat))
                whole.append(xxh64_intdigest(text))
                length.append(len(text))
                total.append(sum(counts))
            lists = [_cells(x, offsets) for x in (np.array(flat, np.uint64), np.array(words, np.int32), np.concatenate(starts).astype(np.int32))]
            return pa.RecordBatch.from_arrays([batch.column("i"), pa.array(np.array(whole, np.uint64).view(np.int64)), pa.array(length, pa.int32()), pa.array(total, pa.int32()), pa.array(np.diff(offsets), pa.int32()), *lists], ["doc", "whole", "length", "total", "n", "units", "words", "starts"])

        return step

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")).where("i is not null and t is not null")
    return common.map_batches(rows, make, "doc long, whole long, length int, total int, n int, units binary, words binary, starts binary", _ROWS)


def _cells(flat: np.ndarray, offsets: list[int]) -> pa.Array:
    """The numbers between two offsets each, as bytes: Spark moves them whole, where it takes arrays apart."""
    return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer((np.array(offsets) * flat.itemsize).astype(np.int32)), pa.py_buffer(flat)])


def _flat(batch: pa.RecordBatch, name: str, kind: type) -> np.ndarray:
    return np.frombuffer(b"".join(batch.column(name).to_pylist()), kind)


def _offsets(batch: pa.RecordBatch) -> np.ndarray:
    """Line at which each document of a batch begins, and the end."""
    return np.append(0, np.cumsum(np.array(batch.column("n"), np.int64)))


@dataclass(frozen=True)
class Places:
    """A run (doc, pos, end) as one value in order of (doc, pos, end): a long if `bits` for each line number and the ids, counted
    from `least`, fit into 63 bits; else a struct, with bits 0."""

    least: int = 0
    bits: int = 0

    @staticmethod
    def of(narrow: DataFrame) -> Places:
        """For documents (doc, n): ids and numbers of lines."""
        least, most, n = narrow.agg(F.min("doc"), F.max("doc"), F.max("n")).first()
        if least is None:
            return Places(0, 1)
        bits = max(1, n.bit_length())
        return Places(least, bits) if (most - least).bit_length() + 2 * bits <= 63 else Places()

    @property
    def type(self) -> str:
        return "long" if self.bits else "struct<doc: long, place: long>"

    def hold(self, doc: np.ndarray, pos: np.ndarray, end: np.ndarray) -> pa.Array:
        if self.bits:
            return pa.array((doc - self.least) << 2 * self.bits | pos << self.bits | end)
        return pa.StructArray.from_arrays([pa.array(doc), pa.array(pos << 32 | end)], ["doc", "place"])

    def columns(self, c: str) -> list[Column]:
        if self.bits:
            doc, place, bits = F.shiftright(c, 2 * self.bits) + F.lit(self.least), F.col(c), self.bits
        else:
            doc, place, bits = F.col(f"{c}.doc"), F.col(f"{c}.place"), 32
        line = (1 << bits) - 1
        return [doc.alias("doc"), F.shiftright(place, bits).bitwiseAND(line).cast("int").alias("pos"), place.bitwiseAND(line).cast("int").alias("end")]


def _seed_rows(table: DataFrame, places: Places, least: int) -> DataFrame:
    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            at = _offsets(batch)
            sizes = np.diff(at)
            name, pos, end = seeds(_flat(batch, "units", np.uint64), _flat(batch, "words", np.int32), np.repeat(at[1:], sizes), least)
            row = np.repeat(np.arange(batch.num_rows), sizes)[pos]
            return pa.RecordBatch.from_arrays([pa.array(name.view(np.int64)), places.hold(np.array(batch.column("doc"))[row], pos - at[row], end - at[row])], ["name", "place"])

        return step

    return common.map_batches(table.select("n", "units", "words", "doc"), make, f"name long, place {places.type}", _ROWS)


def sources(rows: DataFrame) -> DataFrame:
    """(name, first) of names seen more than once: an interval's first place."""
    return rows.groupBy("name").agg(F.count("*").alias("n"), F.min("place").alias("first")).where("n > 1").select("name", "first")


def _with_source(rows: DataFrame, groups: DataFrame, places: Places) -> DataFrame:
    """Rows (name, place) of names seen more than once, taken apart, with later, whether their interval begins before, and further
    columns.  The groups are settled, so that the join with all positions stands alone and a hot name's rows can be split;
    they grow with the corpus, so a hint keeps them from being broadcast at any size."""
    more = [c for c in rows.columns if c not in ("name", "place")]
    return rows.join(groups.hint("shuffle_hash"), "name").select("name", *places.columns("place"), (F.col("place") > F.col("first")).alias("later"), *more)


def doubled(row: np.ndarray, pos: np.ndarray, end: np.ndarray, name: np.ndarray, rounds: int | None = None):
    """For each round (number, row, pos, end, name) of the runs that two runs of the round before make, end to end.  row: which
    document; name: unsigned."""
    order = np.argsort(row << 32 | pos, kind="stable")
    row, pos, end, name = row[order], pos[order], end[order], name[order]
    k = 0
    while rounds is None or k < rounds:
        key, at = row << 32 | pos, row << 32 | end
        lo = np.searchsorted(key, at)
        n = np.searchsorted(key, at, "right") - lo  # more than one only for rows that share an id
        a = np.repeat(np.arange(len(key)), n)
        if not len(a):
            return
        b = np.arange(len(a)) + np.repeat(lo - (np.cumsum(n) - n), n)
        with np.errstate(over="ignore"):
            row, pos, end, name = row[a], pos[a], end[b], mixed(paired(name[a], name[b]))
        if n.max() > 1:
            once = np.sort(np.unique(np.stack([row << 32 | pos, end, name.view(np.int64)]), axis=1, return_index=True)[1])
            row, pos, end, name = row[once], pos[once], end[once], name[once]
        k += 1
        yield k, row, pos, end, name


def joined(row: np.ndarray, pos: np.ndarray, end: np.ndarray, name: np.ndarray):
    """(row, pos, end, name, start) of the last run of each segment, and where that begins: runs of a document that touch or
    overlap.  name: signed."""
    order = np.lexsort((name, end, pos, row))
    row, pos, end, name = row[order], pos[order], end[order], name[order]
    new = np.append(True, (row << 32 | pos)[1:] > np.maximum.accumulate(row << 32 | end)[:-1])[: len(row)]
    segment = np.cumsum(new)
    order = np.lexsort((name, pos, end, segment))  # a segment's runs stay where the segment is
    last = order[np.append(np.flatnonzero(new)[1:], len(row)) - 1] if len(row) else order
    return row[last], pos[last], end[last], name[last], pos[new]


def _joined_and_doubled(level: DataFrame, places: Places, rounds: int | None) -> DataFrame:
    """(name, place, level, start) of the runs of all rounds beyond level 0, start null; and with start those of segments."""
    held = level.groupBy("doc").agg(F.collect_list(F.struct("pos", "end", "name", "later")).alias("runs"))  # one for each line at most

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            runs, doc = batch.column("runs"), np.array(batch.column("doc"))
            row = np.repeat(np.arange(batch.num_rows), np.diff(np.array(runs.offsets)))
            pos, end, name, later = (x.to_numpy(zero_copy_only=False) for x in runs.flatten().flatten())
            pos, end, later = pos.astype(np.int64), end.astype(np.int64), later.astype(bool)
            r, p, e, n, start = joined(row[later], pos[later], end[later], name[later])
            found = [(n, doc[r], p, e, np.full(len(r), -1, np.int32))]
            for k, r, p, e, n in doubled(row, pos, end, name.view(np.uint64), rounds):
                found.append((n.view(np.int64), doc[r], p, e, np.full(len(r), k, np.int32)))
            name, doc, pos, end, depth = (np.concatenate(x) for x in zip(*found))
            return pa.RecordBatch.from_arrays([pa.array(name), places.hold(doc, pos, end), pa.array(depth), pa.concat_arrays([pa.array(start, pa.int32()), pa.nulls(len(name) - len(start), pa.int32())])], ["name", "place", "level", "start"])

        return step

    return common.map_batches(held, make, f"name long, place {places.type}, level int, start int", _ROWS)


def _ranges(steps: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Offsets of lists of these lengths, and for each entry where its list begins and its number from 1."""
    offsets = np.append(0, np.cumsum(steps))
    return offsets, np.repeat(at, steps), np.arange(1, offsets[-1] + 1) - np.repeat(offsets[:-1], steps)


def _answers(table: DataFrame, requests: DataFrame, least_words: int) -> DataFrame:
    """The requests (doc, at, pos, name, last) with off, where line `at` starts; more: for the lines from there on that have
    fewer than least_words words together, a hash of the first, of the first two and so on; more_end: for last ones the
    characters at which those lines end."""
    asked = requests.groupBy("doc").agg(F.collect_list(F.struct("at", "pos", "name", "last")).alias("asked"))  # a few for each line at most

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            units, words, starts = _flat(batch, "units", np.uint64), _flat(batch, "words", np.int32), _flat(batch, "starts", np.int32)
            asked, first = batch.column("asked"), _offsets(batch)
            row = np.repeat(np.arange(batch.num_rows), np.diff(np.array(asked.offsets)))
            requests = dict(zip([f.name for f in asked.type.value_type], asked.flatten().flatten()))
            stops = np.insert(starts, first[1:], np.array(batch.column("length")))  # one more for each document than lines
            at = np.minimum(first[row] + np.array(requests["at"]), first[row + 1])
            total = np.append(0, np.cumsum(words, dtype=np.int64))
            to = np.minimum(np.searchsorted(total, total[at] + least_words), first[row + 1])
            last = np.array(requests["last"].to_numpy(zero_copy_only=False), bool)
            steps = np.where(np.array(requests["name"].is_valid()), to - at, 0)
            offsets, begin, k = _ranges(steps, at)
            with np.errstate(over="ignore"):
                sums = np.append(np.uint64(0), np.cumsum(units * powers(_BASE, len(units))[: len(units)], dtype=np.uint64))
                chain = mixed((sums[begin + k] - sums[begin]) * powers(_INVERSE, len(units))[begin] + k.astype(np.uint64))
            end_offsets, begin, k = _ranges(np.where(last, steps, 0), at + row)
            lists = [pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(chain.view(np.int64))), pa.ListArray.from_arrays(pa.array(end_offsets, pa.int32()), pa.array(stops[begin + k], pa.int32()))]
            return pa.RecordBatch.from_arrays([batch.column("doc").take(pa.array(row)), *[requests[c] for c in ("at", "pos", "name", "last")], pa.array(stops[at + row], pa.int32()), *lists], ["doc", "at", "pos", "name", "last", "off", "more", "more_end"])

        return step

    return common.map_batches(table.select("doc", "length", "n", "units", "words", "starts").join(asked, "doc"), make, "doc long, at int, pos int, name long, last boolean, off int, more array<long>, more_end array<int>", _ROWS)


def repeated_runs(docs: DataFrame, least_words: int = LEAST_WORDS, id_col: str = "doc_id", text_col: str = "text", rounds: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(runs, sizes).  runs: (doc, start, end, from_char, to_char, level), maximal runs of lines that occur before; a copy
    of a whole document has level -1.  sizes: (doc, n) lines of each document."""
    lines = common.settle(_line_table(docs, id_col, text_col), "lines")
    narrow = lines.select("doc", "whole", "length", "total", "n")
    firsts = narrow.where(F.col("total") >= least_words).groupBy("whole").agg(F.min("doc").alias("fdoc"), F.count("*").alias("copies")).where("copies > 1").select("whole", "fdoc")
    copies = common.settle(narrow.join(firsts, "whole").where("fdoc < doc").select("doc", F.lit(0).alias("start"), F.col("n").alias("end"), F.lit(0).alias("from_char"), F.col("length").alias("to_char"), F.lit(-1).alias("level")), "copies")
    table = common.settle(lines.select("doc", "length", "n", "units", "words", "starts").join(copies.select("doc").distinct().hint("shuffle_hash"), "doc", "left_anti"), "own-lines")
    sizes = common.settle(narrow.select("doc", "n"), "line-counts")
    places = Places.of(narrow)
    common.discard(lines)
    rows = _seed_rows(table, places, least_words)
    groups = common.settle(sources(rows), "sources")
    level = common.settle(_with_source(rows, groups, places), "level")
    common.discard(groups)
    found = common.settle(_joined_and_doubled(level, places, rounds), "doubled")
    segments = common.settle(found.where("start is not null").select("start", *places.columns("place"), "name"), "segments")
    deepest = segments.select("doc", F.lit(0).alias("level"))  # each document with a later run has a segment
    deeper = None
    if rounds != 0:
        rows = found.where("start is null").select("name", "place", "level")
        deeper = common.settle(sources(rows), "sources")
        deepest = deepest.union(_with_source(rows, deeper, places).where("later").select("doc", "level"))
    deepest = common.settle(deepest.groupBy("doc").agg(F.max("level").alias("level")), "levels")
    for used in (found, deeper):
        if used is not None:
            common.discard(used)
    # all places of the segments' last runs, longer by a line, by two and so on: a name for each, grouped as before;
    # places that go on alike are one before they are taken apart
    lasts = segments.select("doc", "pos", F.lit(True).alias("last"))
    others = level.join(segments.select("name").distinct(), "name").join(lasts, ["doc", "pos"], "left")
    requests = segments.select("doc", F.col("start").alias("at"), F.lit(None).cast("int").alias("pos"), F.lit(None).cast("long").alias("name"), F.lit(False).alias("last")).distinct()
    requests = requests.union(others.select("doc", F.col("end").alias("at"), "pos", "name", F.coalesce("last", F.lit(False)).alias("last")))
    answers = common.settle(_answers(table, requests, least_words), "answers")
    alike = answers.where("name is not null").groupBy("name", F.xxhash64("more").alias("way")).agg(F.min(F.struct("doc", "pos")).alias("first"), F.first("more").alias("more"))
    firsts = alike.select("name", "first", F.explode("more").alias("x")).groupBy(F.xxhash64("name", "x").alias("longer")).agg(F.min("first").alias("first"))
    firsts = common.settle(firsts, "firsts")  # so that a hot way's rows can be split in the join
    own = answers.where("last").select("doc", "pos", "name", F.posexplode("more").alias("k", "x")).select("doc", "pos", (F.col("k") + 1).alias("k"), F.xxhash64("name", "x").alias("longer"))
    reach = own.join(firsts.hint("shuffle_hash"), "longer").where(F.col("first") < F.struct("doc", "pos")).groupBy("doc", "pos").agg(F.max("k").alias("k"))
    begin = answers.where("name is null").select("doc", F.col("at").alias("start"), F.col("off").alias("from_char"))
    runs = segments.join(reach, ["doc", "pos"], "left").withColumn("k", F.coalesce("k", F.lit(0)))
    runs = runs.join(begin, ["doc", "start"]).join(answers.where("last").select("doc", "pos", "off", "more_end"), ["doc", "pos"])
    runs = runs.select("doc", "start", (F.col("end") + F.col("k")).alias("end"), "from_char", F.when(F.col("k") > 0, F.element_at("more_end", F.greatest("k", F.lit(1)))).otherwise(F.col("off")).alias("to_char")).join(deepest, "doc")
    out = common.settle(runs.union(copies), "runs"), sizes
    for used in (table, answers, segments, copies, level, deepest, firsts):
        common.discard(used)
    return out


def drop_repeats(docs: DataFrame, least_words: int = LEAST_WORDS, id_col: str = "doc_id", text_col: str = "text", rounds: int | None = None) -> DataFrame:
    """docs, all columns, with text cut, and counts __lines and __removed, and __level, the deepest level of its runs."""
    runs, sizes = repeated_runs(docs, least_words, id_col, text_col, rounds)
    cuts = runs.groupBy("doc").agg(F.array_sort(F.collect_list(F.struct("from_char", "to_char", "start", "end"))).alias("__cut"), F.max("level").alias("__level"))
    sizes = sizes.groupBy("doc").agg(F.max("n").alias("__lines")).join(cuts, "doc", "left").withColumnRenamed("doc", "__doc")
    both = docs.join(sizes.hint("shuffle_hash"), F.col(id_col).cast("long") == F.col("__doc"), "left")
    text = F.col(text_col)
    start = F.struct(F.lit(0).alias("at"), F.lit(0).alias("line"), F.lit(0).alias("gone"), F.lit("").alias("out"))

    def step(a, x):
        piece = F.substring(text, a["at"] + 1, F.greatest(x["from_char"] - a["at"], F.lit(0)))
        gone = F.greatest(x["end"] - F.greatest(x["start"], a["line"]), F.lit(0))
        return F.struct(F.greatest(a["at"], x["to_char"]).alias("at"), F.greatest(a["line"], x["end"]).alias("line"), (a["gone"] + gone).alias("gone"), F.concat(a["out"], piece).alias("out"))

    both = both.withColumn("__left", F.aggregate("__cut", start, step))
    cut = F.regexp_replace(F.concat(F.col("__left.out"), F.substring(text, F.col("__left.at") + 1, F.length(text))), r"\s+$", "")
    return both.select(*[F.when(F.col("__cut").isNotNull(), cut).otherwise(text).alias(c) if c == text_col else F.col(c) for c in docs.columns], F.coalesce("__lines", F.lit(0)).cast("long").alias("__lines"), F.coalesce("__left.gone", F.lit(0)).cast("long").alias("__removed"), "__level")
