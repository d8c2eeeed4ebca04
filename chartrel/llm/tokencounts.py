"""Token counts as delta-maintained rollups by source, language and tokenizer version.

A batch holds signed changes: ``insert`` adds a document's tokens, ``delete`` takes them off, ``revise`` takes off what
was counted before and adds the new count. Every batch is reduced to one delta per (source, language, version) and
written under its own id; pending deltas are merged into a table of totals with a version of its own. A batch is
committed by a marker that is written last, so a lost job leaves no delta, a repeated one overwrites its own leavings, and a
batch that is already committed, merged or not, is left as it is. One writer at a time merges.

Defined results: a null text has no tokens and is still counted as a document; null sources and languages are groups of
their own. A repeated row counts each time. Null ``tokens`` and ``old_tokens`` count as zero; a row whose op is null or
none of the three changes nothing. A delete of what was never inserted gives negative totals, which are kept.
Groups whose documents and tokens are both zero are dropped from the rollup. An empty batch commits no delta rows. Extra
columns are ignored.
"""

from __future__ import annotations

import base64
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WORD, sliced, text_batches

#: Pending batches at which they are merged into the totals.
MERGE_EVERY = 8
DELTA = "source string, lang string, tokenizer string, docs long, tokens long"
#: The pattern by which the public byte-level vocabularies cut text before merging (fixed values).
CUT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


@lru_cache(maxsize=2)
def _encoding(vocabulary: bytes):
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in vocabulary.splitlines())}
    return tiktoken.Encoding("own", pat_str=CUT, mergeable_ranks=ranks, special_tokens={})


def counted(docs: DataFrame, vocabulary: str) -> DataFrame:
    """Columns of ``docs`` but the text, with ``tokens``: byte-level BPE tokens of the whole text. The driver reads the vocabulary file."""
    text_batches(docs.sparkSession)
    names = [c for c in docs.columns if c not in ("text", "tokens")]
    with open(vocabulary, "rb") as f:
        shared = docs.sparkSession.sparkContext.broadcast(f.read())  # a file of fixed size

    def run(batches):
        enc = _encoding(shared.value)
        for batch in sliced(batches):
            n = [len(enc.encode_ordinary(t)) if t else 0 for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(n, pa.int64())], names=[*names, "tokens"])

    kinds = dict(docs.dtypes)
    return docs.select(*names, "text").mapInArrow(run, ", ".join([*(f"`{c}` {kinds[c]}" for c in names), "tokens long"]))


def words(docs: DataFrame) -> DataFrame:
    """The same by blank-delimited words, without Python."""
    return docs.select(*[c for c in docs.columns if c not in ("text", "tokens")], F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("tokens"))


def deltas(changes: DataFrame, tokenizer: str | Column) -> DataFrame:
    """One row per group from changes: source, lang, op, tokens, and old_tokens where op is ``revise``."""
    count = lambda c: F.coalesce(F.col(c), F.lit(0))
    sign = F.when(F.col("op") == "insert", 1).when(F.col("op") == "delete", -1).otherwise(0)
    moved = F.when(F.col("op") == "revise", count("tokens") - count("old_tokens")).otherwise(sign * count("tokens"))
    name = F.lit(tokenizer) if isinstance(tokenizer, str) else tokenizer
    return changes.groupBy("source", "lang", name.alias("tokenizer")).agg(F.sum(sign).cast("long").alias("docs"), F.sum(moved).cast("long").alias("tokens"))


class Rollup:
    """Totals and the deltas not yet in them, under ``path`` of any store that Spark writes.

    ``batch=<id>`` holds one batch's delta, ``totals=<n>`` version n of the totals with the names of all batches in it.
    Either counts from its ``committed`` file on, which is written last, whatever the session's committer leaves. Every
    ``every`` batches the pending deltas are merged into the next version and deleted, so what ``totals`` reads does not grow with history.
    """

    def __init__(self, spark: SparkSession, path: str, every: int = MERGE_EVERY):
        self.spark, self.path, self.every = spark, path.rstrip("/"), every
        self._at = spark._jvm.org.apache.hadoop.fs.Path
        self._fs = self._at(self.path).getFileSystem(spark._jsc.hadoopConfiguration())

    def _named(self, kind: str) -> list[str]:
        if not self._fs.exists(self._at(self.path)):
            return []
        names = (s.getPath().getName() for s in self._fs.listStatus(self._at(self.path)))
        return sorted(n.removeprefix(kind) for n in names if n.startswith(kind) and self._fs.exists(self._at(f"{self.path}/{n}/committed")))

    def _commit(self, folder: str) -> None:
        self._fs.create(self._at(f"{self.path}/{folder}/committed"), True).close()

    def version(self) -> int:
        """Newest committed version of the totals; 0 before the first."""
        return max(map(int, self._named("totals=")), default=0)

    def _merged(self, version: int) -> set[str]:
        return {r["batch"] for r in self.spark.read.schema("batch string").parquet(f"{self.path}/totals={version}/batches").collect()} if version else set()

    def pending(self) -> list[str]:
        """Committed batches that the newest totals do not hold."""
        merged = self._merged(self.version())
        return [b for b in self._named("batch=") if b not in merged]

    def batches(self) -> list[str]:
        """All batches ever committed."""
        return sorted(self._merged(self.version()) | set(self._named("batch=")))

    def apply(self, batch: str, delta: DataFrame) -> bool:
        """Commits a batch of deltas once; False if it was committed before."""
        if batch in self.batches():
            return False
        delta.select(*(x.split()[0] for x in DELTA.split(", "))).write.mode("overwrite").parquet(f"{self.path}/batch={batch}/rows")
        self._commit(f"batch={batch}")
        if len(self.pending()) >= self.every:
            self.merge()
        return True

    def merge(self) -> int:
        """Writes the next version of the totals, then deletes what it replaces; a lost job leaves the old version in force."""
        old, every = self.version(), self.batches()
        new = old + 1
        self.totals().write.mode("overwrite").parquet(f"{self.path}/totals={new}/rows")
        self.spark.createDataFrame([(b,) for b in every], "batch string").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/totals={new}/batches")
        self._commit(f"totals={new}")
        for folder in [f"batch={b}" for b in self._named("batch=") if b in every] + [f"totals={v}" for v in self._named("totals=") if int(v) < new]:
            self._fs.delete(self._at(f"{self.path}/{folder}"), True)
        return new

    def totals(self) -> DataFrame:
        """source, lang, tokenizer, docs, tokens over committed batches: the newest version and the pending deltas."""
        old = self.version()
        at = [f"{self.path}/totals={old}/rows"] * bool(old) + [f"{self.path}/batch={b}/rows" for b in self.pending()]
        rows = self.spark.read.schema(DELTA).parquet(*at) if at else self.spark.createDataFrame([], DELTA)
        out = rows.groupBy("source", "lang", "tokenizer").agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        return out.filter("docs <> 0 or tokens <> 0")
