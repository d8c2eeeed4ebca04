"""Helpers shared by the operators: shared-folder tables, fold expressions, text batches."""

from __future__ import annotations

import ctypes
import gc
import os
import tempfile
import uuid
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: What ends a word everywhere in this subpackage: ASCII space and the five ASCII controls 9 to 13.
WORD = r"[^\x20\x09-\x0D]+"
#: Rows of an Arrow batch that holds whole texts.
TEXT_ROWS = 1000


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """One of the given tables, pruned to ``cols`` at the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as the session names it; a temporary one only in local mode without any."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if at:
        return at.rstrip("/")
    if (own := spark.sparkContext._jsc.sc().getCheckpointDir()).isDefined():
        return str(own.get())
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir names no folder that driver and executors share")
    at = os.path.join(tempfile.gettempdir(), "chartrel-shared")
    spark.sparkContext.setCheckpointDir(at)
    return at


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once to the shared folder and read back: lineage is cut, and a lost executor costs a reread."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class Scratch:
    """Intermediate tables of one run, in a folder of their own that goes when the result is stored elsewhere."""

    def __init__(self, spark: SparkSession):
        self.spark, self.path, self.n = spark, f"{shared_dir(spark)}/run-{uuid.uuid4().hex}", 0

    def __call__(self, df: DataFrame, name: str) -> DataFrame:
        self.n += 1
        path = f"{self.path}/{self.n}-{name}"
        df.write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def result(self, df: DataFrame, name: str) -> DataFrame:
        """``df`` stored beside the run, and the run's folder deleted."""
        out = stored(df, name)
        self.clear()
        return out

    def clear(self) -> None:
        delete(self.spark, self.path)


@contextmanager
def arrow_rows(spark: SparkSession, n: int):
    """Rows per Arrow batch while something is written: few where a row holds whole texts. The session's own number returns."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    old = spark.conf.get(key)
    spark.conf.set(key, n)
    try:
        yield
    finally:
        spark.conf.set(key, old)


def trim() -> None:
    """Gives freed memory back to the system: a worker that is used again starts small."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library keeps what it likes
        pass


def sliced(batches, rows: int = 512, least: int = 0):
    """Arrow batches in short runs of rows, so that few texts are Python objects at a time.

    ``least``: bytes of input up to which a task leaves memory as it is, as trimming takes longer than a small task's work.
    """
    seen = 0
    if not least:
        trim()
    for batch in batches:
        if seen < least <= seen + batch.nbytes:
            trim()
        seen += batch.nbytes
        for lo in range(0, batch.num_rows, rows):
            yield batch.slice(lo, rows)
    if seen >= least:
        trim()


def text_batches(spark: SparkSession) -> None:
    """Holds this session's Arrow batches to TEXT_ROWS rows, as whole texts make the default's batches large on both sides."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= TEXT_ROWS:
        spark.conf.set(key, TEXT_ROWS)


def discard(df: DataFrame) -> None:
    """Deletes what ``stored`` wrote, once nothing reads it any more."""
    for parent in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        delete(df.sparkSession, parent)


def delete(spark: SparkSession, at: str) -> None:
    """Deletes a folder of any store that Spark writes."""
    path = spark._jvm.org.apache.hadoop.fs.Path(at)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def parts(spark: SparkSession) -> int:
    """Partitions for a spread that no key calls for: the session's shuffle width, two per core at least."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)


def fold(col: str, n: int) -> Column:
    """Fold of a row by the CRC-32 of its id written as text; a null id is in fold 0."""
    return F.coalesce(F.crc32(F.col(col).cast("string")) % n, F.lit(0))


def hashed_sample(rows: DataFrame, n: int, *keys: str, salt: int = 0) -> DataFrame:
    """The ``n`` rows of least hash of ``keys``; all rows where there are no more. A bound on the hash comes first, so only about 2n are sorted.

    Rows equal in ``keys`` share a hash: of a table of few such groups, rows of the group of least hash are taken.
    """
    h = F.pmod(F.xxhash64(F.lit(salt), *keys), F.lit(1 << 30))
    total, least = rows.agg(F.count("*"), F.min(h)).first()
    if total <= n:
        return rows
    bound = max(int(2 * n / total * (1 << 30)), least + 1)
    return rows.withColumn("__h", h).filter(F.col("__h") < bound).orderBy("__h", *keys).limit(n).drop("__h")


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """64-bit finaliser with full avalanche (public splitmix constants), elementwise."""
    with np.errstate(over="ignore"):
        x = x.astype(np.uint64) + np.uint64((0x9E3779B97F4A7C15 * (salt + 1)) & 0xFFFFFFFFFFFFFFFF)
        x ^= x >> np.uint64(30)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def slices(lengths, budget: int):
    """Consecutive index ranges whose lengths sum to ``budget`` at most; a longer single item stands alone."""
    start = total = 0
    for i, n in enumerate(lengths):
        if total + n > budget and i > start:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(lengths):
        yield start, len(lengths)
