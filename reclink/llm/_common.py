"""Shared parts of the training-data operators: Arrow text buffers, vectorised word
hashes, shared-folder files and materialised tables."""

from __future__ import annotations

import contextlib
import ctypes
import os
import sys
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reclink.operators.joins import hot_join  # noqa: F401  used by the operators

#: Bytes of text that one vectorised step looks at; a longer text is a step of its own.
STEP_BYTES = 4 << 20
#: Bytes of an Arrow batch on its way to a worker while a step is written.
BATCH_BYTES = 2 << 20
_BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"
#: Bytes that one prefix-sum block of the hasher covers.
HASH_BLOCK = 1 << 20

U64 = np.uint64


# ---------------------------------------------------------------- sessions and files
def shared_dir(spark: SparkSession) -> str:
    """URI of a folder that the driver and all executors share: ``spark.checkpoint.dir``.

    Only where that is unset (tests on one machine) a temporary folder is set up.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        option = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = option.get() if option.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="reclink-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def fresh_uri(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


@contextlib.contextmanager
def small_batches(spark: SparkSession):
    """Arrow batches of BATCH_BYTES while an action runs; the session's setting comes back."""
    before = spark.conf.get(_BATCH)
    spark.conf.set(_BATCH, str(BATCH_BYTES))
    try:
        yield
    finally:
        spark.conf.set(_BATCH, before)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write df to the shared folder and read it back; later plans start from the files."""
    uri = fresh_uri(df.sparkSession, tag)
    with small_batches(df.sparkSession):
        df.write.parquet(uri)
    return df.sparkSession.read.schema(df.schema).parquet(uri)


def local_path(uri: str) -> str | None:
    if uri.startswith("file:"):
        return "/" + uri[5:].lstrip("/")
    return uri if uri.startswith("/") else None


class SharedFile:
    """Random-access reads of a file in the shared folder."""

    def __init__(self, uri: str):
        path = local_path(uri)
        if path:
            self._file, self.size = open(path, "rb"), os.path.getsize(path)
        else:
            from pyarrow import fs

            system, inner = fs.FileSystem.from_uri(uri)
            self._file = system.open_input_file(inner)
            self.size = self._file.size()

    def read_at(self, at: int, length: int) -> bytes:
        self._file.seek(at)
        return self._file.read(length)

    def close(self) -> None:
        self._file.close()


class AtomicWriter:
    """Writes to a name of this attempt and renames at the end, so that a retried or
    speculative task replaces a whole file by an equal whole file."""

    def __init__(self, uri: str):
        self.uri, self.position = uri, 0
        self._part = f"{uri}.{uuid.uuid4().hex}.tmp"
        path = local_path(self._part)
        if path:
            self._system, self._name = None, path
            os.makedirs(os.path.dirname(path), exist_ok=True)
            self._file = open(path, "wb")
        else:
            from pyarrow import fs

            self._system, self._name = fs.FileSystem.from_uri(self._part)
            self._system.create_dir(self._name.rpartition("/")[0], recursive=True)
            self._file = self._system.open_output_stream(self._name)

    def write(self, data) -> None:
        self._file.write(data)
        self.position += len(data)

    def commit(self) -> None:
        self._file.close()
        if self._system is None:
            os.replace(self._name, local_path(self.uri))
        else:
            self._system.move(self._name, self._name[: -len(self._part) + len(self.uri)])


def worker_cache() -> dict:
    """A dict that lives as long as the Python worker process."""
    return sys.__dict__.setdefault("_reclink_worker_cache", {})


def release_memory() -> None:
    """Hand freed memory of this worker back to the system, where the C library can."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):
        pass


def tidy(step):
    """A mapInArrow function that leaves no freed memory behind: workers live on, idle,
    while later stages need their executor's memory."""

    def run(batches):
        try:
            yield from step(batches)
        finally:
            release_memory()

    return run


# ---------------------------------------------------------------- text in Arrow batches
def utf8(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null counts as the empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    kind = np.int64 if wide else np.int32
    _, offsets, data = column.buffers()
    if len(column) == 0 or offsets is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    offsets = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def steps(offsets: np.ndarray, limit: int = STEP_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows with at most `limit` bytes each, or one longer row."""
    at, rows = 0, len(offsets) - 1
    while at < rows:
        to = int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1
        to = min(max(to, at + 1), rows)
        yield at, to
        at = to


def text_steps(column, limit: int = STEP_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    data, offsets = utf8(column)
    for at, to in steps(offsets, limit):
        yield at, to, data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]


# ---------------------------------------------------------------- hashes
def splitmix(x: np.ndarray) -> np.ndarray:
    """The splitmix64 finaliser on an array of unsigned 64-bit integers."""
    with np.errstate(over="ignore"):
        x = x + U64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
        return x ^ (x >> U64(31))


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    with np.errstate(over="ignore"):
        return np.cumprod(out, dtype=np.uint64)


class SpanHasher:
    """64-bit hashes of byte spans: prefix sums of random byte values times powers of an
    odd base modulo 2**64, shifted back by the inverse power and mixed."""

    def __init__(self, seed: int, lower: bool = True):
        table = splitmix(np.arange(256, dtype=np.uint64) + U64(seed * 1000003))
        if lower:
            table[65:91] = table[97:123]
        self.table = table
        self.base = int(splitmix(np.array([seed + 77], np.uint64))[0]) | 1
        self._up = self._down = np.ones(1, np.uint64)

    def _grow(self, n: int) -> None:
        if len(self._up) < n:
            n = max(n, HASH_BLOCK + 1)
            self._up = _powers(self.base, n)
            self._down = _powers(pow(self.base, -1, 1 << 64), n)

    def spans(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Hash of data[s:e] for ascending, non-overlapping spans."""
        out = np.empty(len(starts), np.uint64)
        at = 0
        with np.errstate(over="ignore"):
            while at < len(starts):
                first = int(starts[at])
                to = max(int(np.searchsorted(ends, first + HASH_BLOCK, "right")), at + 1)
                n = int(ends[to - 1]) - first
                self._grow(n + 1)
                sums = np.empty(n + 1, np.uint64)
                sums[0] = 0
                np.cumsum(self.table[data[first : first + n]] * self._up[:n], out=sums[1:])
                s, e = starts[at:to] - first, ends[at:to] - first
                out[at:to] = splitmix((sums[e] - sums[s]) * self._down[s] + (e - s).astype(np.uint64))
                at = to
        return out


#: Separators of the word pattern [^\x20\x09-\x0D]+
BLANK = np.zeros(256, bool)
BLANK[[0x20, *range(0x09, 0x0E)]] = True


def word_spans(data: np.ndarray, offsets: np.ndarray, separators: np.ndarray = BLANK):
    """(starts, ends, first word of each row with one more entry) of the words of all rows."""
    n = len(data)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    inside = ~separators[data]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    begins = inside.copy()
    begins[1:] &= ~inside[:-1] | edge[1:n]
    stops = inside.copy()
    stops[:-1] &= ~inside[1:] | edge[1:n]
    starts, ends = np.flatnonzero(begins), np.flatnonzero(stops) + 1
    return starts, ends, np.searchsorted(starts, offsets)


# ---------------------------------------------------------------- columns
def crc32_text(column) -> "F.Column":
    """crc32 of a value written as text (null: of the empty text)."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")))


def lower_ascii(column):
    return F.translate(column, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def bounded(df: DataFrame, max_rows: int):
    """df with a broadcast hint if it has at most max_rows rows, else as it is: Spark then
    shuffles both sides."""
    return F.broadcast(df) if df.limit(max_rows + 1).count() <= max_rows else df

