"""Tables, image files, label files and sinks."""

from __future__ import annotations

import atexit
import contextlib
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Images of a file of a stored table, and of an Arrow batch: a reader's batch of them stays at some megabytes.
IMAGE_ROWS = 256


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """A given table, pruned to ``cols`` at the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_images(spark: SparkSession, path: str, fmt: str = "binaryFile", glob: str = "*") -> DataFrame:
    """Chart files: packed bytes (``binaryFile``) or decoded by the JVM (``image``, channels in BGR order)."""
    raw = spark.read.format(fmt).option("pathGlobFilter", glob).load(path)
    if fmt == "image":
        return raw.select(F.col("image.origin").alias("path"), F.col("image.width").alias("width"), F.col("image.height").alias("height"), F.col("image.nChannels").alias("channels"), F.col("image.data").alias("data"))
    return raw.select("path", "length", F.col("content").alias("data"))


def labels_json(spark: SparkSession, path: str, schema: str = "chart_id long, series_key string, relation string") -> DataFrame:
    """Labels of a corpus from JSON lines with a stated schema."""
    return spark.read.schema(schema).json(path)


def page_titles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id and title of every page."""
    return table(spark, sf_dir, "pages", "page_id", "html").select("page_id", F.trim(F.regexp_extract("html", "(?is)<title[^>]*>(.*?)</title>", 1)).alias("title"))


def write_relations(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Relations partitioned by relation, so that a search for one reads only its folder."""
    df.write.mode("overwrite").partitionBy("relation").format(fmt).save(path)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as the session names it; a temporary one only in local mode without any."""
    if at := spark.conf.get("spark.checkpoint.dir", None):
        return at.rstrip("/")
    if (own := spark.sparkContext._jsc.sc().getCheckpointDir()).isDefined():
        return str(own.get())
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir names no folder that driver and executors share")
    return os.path.join(tempfile.gettempdir(), "chartrel-shared")


def stored(df: DataFrame) -> DataFrame:
    """``df`` written once to the shared folder and read back: what is planned on it does not hold its lineage. The files go with the driver's process."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    files = df.write.option("maxRecordsPerFile", IMAGE_ROWS) if "data" in df.columns else df.write
    atexit.register(_dropped, spark, path)
    files.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def _dropped(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):  # the JVM may be gone
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def image_batches(spark: SparkSession) -> None:
    """Holds this session's Arrow batches to IMAGE_ROWS rows, as an image has tens of kilobytes."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= IMAGE_ROWS:
        spark.conf.set(key, IMAGE_ROWS)
