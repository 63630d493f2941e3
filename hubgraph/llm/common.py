"""Shared pieces: staging in the cluster's folder, flat byte views of Arrow columns, rolling hashes."""

from __future__ import annotations

import ctypes
import itertools
import os
import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

U64 = np.uint64
BATCH_BYTES, BATCH_SETTING = 4 << 20, "spark.sql.execution.arrow.maxBytesPerBatch"


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a temporary one where it is unset (tests)."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        path = "file://" + os.path.join(tempfile.gettempdir(), "checkpoints")
    return path.rstrip("/")


def stage(df: DataFrame, by: str | None = None) -> DataFrame:
    """Write df to the shared folder and read it back: later steps survive lost executors without recomputation."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/hubgraph-{uuid.uuid4().hex}"
    writer = df.write
    if by:
        writer = writer.partitionBy(by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def in_arrow(df: DataFrame, function, schema: str) -> DataFrame:
    """mapInArrow for df.transform, in bounded memory: batches of BATCH_BYTES (a runtime setting of the session, only
    ever lowered), and a worker, which is reused by later stages, gives back at a partition's end what it has freed."""
    conf = df.sparkSession.conf
    held = conf.get(BATCH_SETTING).lower().removesuffix("b")
    if not held.isdigit() or not 0 < int(held) <= BATCH_BYTES:
        conf.set(BATCH_SETTING, f"{BATCH_BYTES}b")

    def run(batches):
        yield from function(batches)
        give_back()

    return df.mapInArrow(run, schema)


def give_back() -> None:
    """Freed memory of Arrow's pool and of the C library goes back to the system."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_crc(col: str | Column) -> Column:
    """crc32 of the id written as text; a null id counts as the empty text."""
    col = F.col(col) if isinstance(col, str) else col
    return F.crc32(F.coalesce(col.cast("string"), F.lit("")).cast("binary"))


def flat(col) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a text or binary Arrow column, end to end, and len + 1 offsets; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    col = pc.fill_null(col.cast(pa.large_binary()), b"")
    _, offsets, data = col.buffers()
    off = np.frombuffer(offsets, np.int64)[col.offset : col.offset + len(col) + 1] if len(col) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def slices(batches, text: str, limit: int):
    """Cut record batches so that each part holds about `limit` bytes of `text`, or one row if that is longer."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < n:
            base = size[at - 1] if at else 0
            end = max(at + 1, int(np.searchsorted(size, base + limit, side="right")))
            yield batch.slice(at, end - at)
            at = end


def slice_names():
    """Names for the slices of a task, in order. A task that runs again after an executor is lost gives the same names,
    so what other tasks have already fetched of its first run still fits. The rows must come in the same order, as they
    do from files."""
    context = TaskContext.get()
    return (f"{context.partitionId() if context else 0}-{k}" for k in itertools.count())


def packed(*arrays: np.ndarray) -> bytes:
    """Arrays as one compressed string."""
    body = b"".join(len(a).to_bytes(4, "little") + a.dtype.char.encode() + a.tobytes() for a in arrays)
    return zstandard.ZstdCompressor(level=1).compress(body)


def unpacked(blob: bytes) -> list[np.ndarray]:
    body, out, at = zstandard.ZstdDecompressor().decompress(blob), [], 0
    while at < len(body):
        n, kind = int.from_bytes(body[at : at + 4], "little"), np.dtype(chr(body[at + 4]))
        out.append(np.frombuffer(body, kind, n, at + 5))
        at += 5 + n * kind.itemsize
    return out


LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


class Rolling:
    """Hashes of substrings of an array from prefix sums modulo 2**64, all substrings at once."""

    def __init__(self, base: int):
        self.base, self.inverse = base | 1, pow(base | 1, -1, 1 << 64)
        self.up = self.down = np.ones(1, U64)

    def _grow(self, n: int) -> None:
        if len(self.up) < n:
            size = 1 << (n - 1).bit_length()
            for name, b in (("up", self.base), ("down", self.inverse)):
                steps = np.full(size, U64(b))
                steps[0] = 1
                setattr(self, name, np.cumprod(steps, dtype=U64))

    def prefix(self, values: np.ndarray) -> np.ndarray:
        self._grow(len(values) + 1)
        out = np.zeros(len(values) + 1, U64)
        np.cumsum(values * self.up[: len(values)], out=out[1:], dtype=U64)
        return out

    def spans(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((prefix[end] - prefix[start]) * self.down[start])


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> U64(29))) * U64(0x9E3779B97F4A7C15)
    h ^= h >> U64(32)
    return h


#: A random odd-looking value for each byte, so that short strings spread over 64 bits.
BYTE_VALUES = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.uint64)
