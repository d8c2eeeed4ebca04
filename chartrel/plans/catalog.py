"""A catalogue of relations to search: which variables were found related, and how."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "chart_id long, x_label string, y_label string, series_label string, relation string"


def save(tuples: DataFrame, path: str, mode: str = "append") -> None:
    """4-tuples partitioned by relation and sorted by axis label, so that searches prune folders and row groups."""
    rows = tuples.select(*(c.split()[0] for c in SCHEMA.split(", ")))
    rows.repartition("relation", F.pmod(F.xxhash64("x_label"), F.lit(16))).sortWithinPartitions("x_label").write.mode(mode).partitionBy("relation").parquet(path)


def search(spark: SparkSession, path: str, relation: str | None = None, x: str | None = None, y: str | None = None, within: int = 0) -> DataFrame:
    """Tuples by relation and axis labels; ``within`` allows that many edits per label."""
    df = spark.read.schema(SCHEMA).parquet(path)
    if relation:
        df = df.filter(F.col("relation") == relation)
    for c, want in (("x_label", x), ("y_label", y)):
        if want is not None:
            df = df.filter(F.col(c) == want if not within else F.levenshtein(F.col(c), F.lit(want), within) >= 0)
    return df
