"""Five stages from raw documents to a source mix; each reads what the one before wrote and keeps clean documents whole.

The result is one row per document of the last stage, with the words taken and their shards. The texts of the mix, in
the order in which training reads them, are under ``mix-...`` in the folder that driver and executors share.

Defined results: nulls, empty and repeated rows are treated as the stages' operators state in their docstrings; extra
columns pass through all stages but the last. ``n_chars``, where present, follows the text.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chartrel.llm import decontam, linededup, minhash, mixing, toxicity
from chartrel.llm.common import shared_dir, stored, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.without_toxic(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = linededup.dedup_lines(docs, min_tokens=1)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("dropped_lines") > 0, F.length("text").cast(dict(docs.dtypes)["n_chars"])).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash.dedup(docs)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What the mix takes of every document; the mix itself, shuffled by shard, is written to a folder of its own."""
    layout, held, by_source = mixing.mix_sources(mixing.sized(docs))
    mixing.shuffled_mix(docs, layout, by_source).write.parquet(f"{shared_dir(spark)}/mix-{uuid.uuid4().hex}")
    return mixing.taken_by_document(layout, held, by_source)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_repeated_lines),
    ("near_dedup", drop_near_copies),
    ("decontamination", drop_benchmark_leaks),
    ("mixing", mix),
]

#: No SQL: the first stage is a trained network. Tests compare line dedup, near-dedup, decontamination and mixing with brute force and the network with held-out labels.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages applied to ``documents``, each one's result written and reread."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
