"""Media columns: payloads in archives, read by a Spark data source over byte ranges.

An archive is a run of members.  A member is a header line `doc_id n_bytes media_bytes\n` in fixed-width digits and one
greyscale PNG, 24 samples wide, whose samples are the payload.  Beside each archive lies an index of member offsets and checksums.  The
data source plans partitions as byte ranges over the archives of a folder; a range owns the members that start in it.  Each
member is read by its offset, held against its checksum and retried by itself, so a failed or damaged read repeats one member and not the range; payloads leave
in Arrow batches bounded by bytes.

Null text counts as empty; payloads are padded with bytes 255 to a positive multiple of 576.  Repeated rows are members of
their own; equal texts give equal bytes.  A null id is kept as null.  An empty table gives empty archives and no rows.
"""

from __future__ import annotations

import hashlib
import struct
import time
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from . import common

UNIT = 576
WIDTH = 24
HEAD = 63
SCHEMA = "doc_id long, n_bytes long, media binary"
SIGNATURE = b"\x89PNG\r\n\x1a\n"  # fixed value of the format


def chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def padded(raw: bytes) -> bytes:
    return raw + b"\xff" * (-len(raw) % UNIT or (0 if raw else UNIT))


def to_png(payload: bytes) -> bytes:
    """8-bit greyscale, WIDTH samples a row, no filter, so decoding gives the payload back."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    lines = np.concatenate([np.zeros((len(rows), 1), np.uint8), rows], 1).tobytes()
    return SIGNATURE + chunk(b"IHDR", struct.pack(">IIBBBBB", WIDTH, len(rows), 8, 0, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(lines, 3)) + chunk(b"IEND", b"")


def from_png(media: bytes) -> bytes:
    if media[:8] != SIGNATURE:
        raise ValueError("not a PNG")
    at, data, width = 8, [], 0
    while at < len(media):
        (n,) = struct.unpack_from(">I", media, at)
        kind, body = media[at + 4 : at + 8], media[at + 8 : at + 8 + n]
        if zlib.crc32(kind + body) != struct.unpack_from(">I", media, at + 8 + n)[0]:
            raise ValueError("chunk checksum")
        if kind == b"IHDR":
            width, _, depth, colour = struct.unpack_from(">IIBB", body)
            if (depth, colour) != (8, 0):
                raise ValueError("only 8-bit greyscale")
        elif kind == b"IDAT":
            data.append(body)
        at += 12 + n
    lines = np.frombuffer(zlib.decompress(b"".join(data)), np.uint8).reshape(-1, width + 1)
    if lines[:, 0].any():
        raise ValueError("only rows without filter")
    return lines[:, 1:].tobytes()


def feature_of(payload: bytes) -> str:
    """Mean, deviation and an 8 x 8 hash of block means against their median."""
    x = np.frombuffer(payload, np.uint8)
    cells = np.add.reduceat(x.astype(np.int64), np.arange(0, 64) * len(x) // 64) / np.diff(np.append(np.arange(0, 64) * len(x) // 64, len(x)))
    bits = int("".join("1" if c > np.median(cells) else "0" for c in cells), 2)
    return f"{x.mean():.4f}:{x.std():.4f}:{bits:016x}"


def at_uri(folder: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(folder if ":" in folder.split("/")[0] else f"file://{folder}")


def write_archives(docs: DataFrame, folder: str, id_col: str = "doc_id", text_col: str = "text") -> int:
    """One archive for each task, put in place by one move, so a task that runs again or twice leaves one file.  Returns
    the number of members."""

    def run(batches):
        where, base = at_uri(folder)
        task = TaskContext.get()
        name, n, at, offsets, sums = f"{base}/{task.partitionId():06d}", 0, 0, [], []
        part = f"{base}/.{task.partitionId():06d}-{task.taskAttemptId()}"
        with where.open_output_stream(part) as out:
            for batch in batches:
                for doc_id, text in zip(batch.column("i").to_pylist(), common.texts_of(batch, "t")):
                    raw = text.encode()
                    media = to_png(padded(raw))
                    head = f"{'' if doc_id is None else doc_id:>20} {len(raw):>20} {len(media):>20}\n".encode()
                    offsets.append(at)
                    sums.append(zlib.crc32(head + media))
                    out.write(head + media)
                    at, n = at + HEAD + len(media), n + 1
        with where.open_output_stream(f"{part}.idx") as out:
            out.write(np.array([*offsets, at, *sums], "<i8").tobytes())
        where.move(f"{part}.idx", f"{name}.idx")
        where.move(part, f"{name}.arc")
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])

    where, base = at_uri(folder)
    where.create_dir(base)
    got = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")).mapInArrow(run, "n long").agg(F.sum("n")).first()[0]
    return int(got or 0)


@dataclass
class ByteRange(InputPartition):
    archive: str
    start: int
    stop: int


class ArchiveReader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder, self.span = options["path"], int(options.get("rangebytes", 32 << 20))
        self.tries, self.batch = int(options.get("tries", 3)), int(options.get("batchbytes", 8 << 20))

    def partitions(self) -> list[ByteRange]:
        where, base = at_uri(self.folder)
        files = [f for f in where.get_file_info(fs.FileSelector(base)) if f.path.endswith(".arc")]
        return [ByteRange(f.path, lo, min(lo + self.span, f.size)) for f in sorted(files, key=lambda f: f.path) for lo in range(0, max(f.size, 1), self.span)]

    def member(self, source, offset: int, stop: int, crc: int | None = None) -> tuple:
        """One member by its offset, held against its checksum and tried again by itself."""
        for left in range(self.tries - 1, -1, -1):
            try:
                source.seek(offset)
                raw = source.read(stop - offset)
                doc_id, n, size = raw[:20].strip(), int(raw[21:41]), int(raw[42:62])
                if len(raw) != HEAD + size:
                    raise OSError(f"{len(raw)} bytes at {offset}, not {HEAD + size}")
                if crc is not None and zlib.crc32(raw) != crc:
                    raise OSError(f"damaged bytes at {offset}")
                return (int(doc_id) if doc_id else None), n, raw[HEAD:]
            except (OSError, ValueError):
                if not left:
                    raise
                time.sleep(0.2)

    def read(self, part: ByteRange):
        where, _ = at_uri(self.folder)
        with where.open_input_stream(part.archive[: -len("arc")] + "idx") as f:
            index = np.frombuffer(f.read(), "<i8")
        offsets, sums = index[: len(index) // 2 + 1], index[len(index) // 2 + 1 :]
        lo, hi = np.searchsorted(offsets[:-1], [part.start, part.stop])
        rows, held = [], 0
        with where.open_input_file(part.archive) as source:
            for k in range(lo, hi):
                rows.append(self.member(source, int(offsets[k]), int(offsets[k + 1]), int(sums[k])))
                held += len(rows[-1][2])
                if held >= self.batch:
                    yield self.rows(rows)
                    rows, held = [], 0
        if rows:
            yield self.rows(rows)

    @staticmethod
    def rows(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.binary())], ["doc_id", "n_bytes", "media"])


class MediaArchive(DataSource):
    """spark.read.format("media_archive").load(folder); options rangeBytes, batchBytes, tries."""

    @classmethod
    def name(cls) -> str:
        return "media_archive"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> ArchiveReader:
        return ArchiveReader({k.lower(): v for k, v in self.options.items()})


def read_archives(spark: SparkSession, folder: str, **options) -> DataFrame:
    spark.dataSource.register(MediaArchive)
    return spark.read.format("media_archive").options(**options).load(folder)


def media_features(members: DataFrame) -> DataFrame:
    """Decode each member and describe it."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            out = []
            for media in batch.column("media").to_pylist():
                payload = from_png(media)
                out.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature_of(payload)))
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), *[pa.array([r[k] for r in out], kind) for k, kind in enumerate(kinds)]], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

        return step

    return common.map_batches(members, make, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
