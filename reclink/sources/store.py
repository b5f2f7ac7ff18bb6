"""Frames written to a folder that driver and executors share, and read back."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator, Sequence
from contextlib import contextmanager
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a temporary folder only where none is set, on one machine."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        option = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = option.get() if option.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="linkage-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


#: Takes a query's shuffle files away as soon as it ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def keep(df: DataFrame, name: str = "step", **options: str) -> DataFrame:
    """df as files: short lineage, and one computation for all later uses.  The shuffle files
    of the step go when it is written, not when the driver happens to collect its garbage.
    options are of the writer."""
    spark = df.sparkSession
    uri = f"{folder(spark)}/{name}-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.options(compression="zstd", **options).parquet(uri)
    finally:
        spark.conf.set(CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(uri)
    out._kept = [uri]
    return out


@contextmanager
def small_methods(spark: SparkSession) -> Iterator[None]:
    """Steps of long expressions: the JVM only interprets methods over 8,000 bytes, so beyond that
    Spark's code is made in small ones."""
    name = "spark.sql.codegen.hugeMethodLimit"
    before = spark.conf.get(name)
    spark.conf.set(name, "8000")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def is_kept(df: DataFrame) -> bool:
    return "_kept" in df.__dict__


def release(*frames: DataFrame) -> None:
    """Deletes the files of written frames that nothing reads any more."""
    for df in frames:
        for uri in df.__dict__.pop("_kept", []):
            path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(uri)
            path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


#: Bytes of files from which a step is taken in slices, and slices at most.
SLICE_BYTES, SLICES = 64 << 20, 8


def read_bytes(*frames: DataFrame) -> int:
    """Bytes of the files that frames read."""
    total = 0
    for df in frames:
        leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
        sizes = [int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size())]
        total += sum(x for x in sizes if x < 1 << 60)  # more: not known
    return total


def slices_of(*frames: DataFrame) -> int:
    """Slices in which to take a step, from the bytes of the files that its frames read."""
    return min(SLICES, 1 + read_bytes(*frames) // SLICE_BYTES)


def part(rows: DataFrame, key: str, i: int, n: int) -> DataFrame:
    """Slice i of n, by a hash of the key."""
    return rows if n == 1 else rows.where(F.pmod(F.xxhash64(key), F.lit(n)) == i)


def in_slices(make: Callable[[int], DataFrame], n: int, name: str, **options: str) -> DataFrame:
    """The union of make(0) to make(n - 1), each written before the next begins, so that the
    shuffle files of one slice are there at a time."""
    return together([keep(make(i), name, **options) for i in range(n)])


def together(done: Sequence[DataFrame]) -> DataFrame:
    """The union of written frames, read by one scan where they have the same columns, so that
    plans and their number of tasks do not grow with the frames."""
    uris = [uri for x in done for uri in x._kept]
    same = len(done) > 1 and all([(c.name, c.dataType) for c in x.schema] == [(c.name, c.dataType) for c in done[0].schema] for x in done)
    out = done[0].sparkSession.read.schema(done[0].schema).parquet(*uris) if same else reduce(DataFrame.unionByName, done)
    out._kept = uris
    return out


Keeper = Callable[[DataFrame, str], DataFrame]
