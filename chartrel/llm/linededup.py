"""Line dedup by a fixed-depth log-template tree, in DataFrame operations only.

A line is cut at spaces into tokens; tokens that hold a digit are variable fields and become one wildcard. The
tree routes a line by its token count and its leading tokens; at the leaf, templates that agree outside one of four
runs of positions are one template, so each line carries the hash of its full template and of the four with one run
left open. A template that occurs in two or more documents is recurring: its lines stay in the first document (smallest
id) and are dropped from all others. Recurrence is a minimum and a maximum of document ids per template, so a template
of any number of lines is combined before it is shuffled.

Lines of fewer tokens than leading tokens and runs have their full template only. A line of fewer than ``MIN_TOKENS``
tokens whose fields hide more than ``HIDDEN`` bytes, or leave no letter outside, is its own template: a lone number or an
unspaced passage with a digit in it recurs only where it recurs as it is.

Defined results: lines are separated by line feeds. Blank lines and lines of fewer than ``min_tokens`` tokens are never
dropped (the queries take every line, from one token), and a null or empty text is returned as it is. Rows of equal id count as one document and lose the same lines; a null id takes
no part and is returned unchanged. A text of which every line is dropped becomes empty. Other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch

#: Tree depth below the token count, tokens from which fields are always variable, runs of positions at a leaf.
LEADING, MIN_TOKENS, RUNS = 3, 8, 4
#: Bytes that the fields of a shorter line may hide.
HIDDEN = 64


def tokens_of(line: Column) -> Column:
    """Tokens of a line with variable fields replaced by the wildcard."""
    masked = F.when(line.rlike("[0-9]"), F.regexp_replace(line, r"[^\x20\x09-\x0D0-9]*+[0-9][^\x20\x09-\x0D]*+", "<*>")).otherwise(line)
    tokens, own = F.array_remove(F.split(masked, " "), ""), F.array_remove(F.split(line, " "), "")
    rest = F.replace(masked, F.lit("<*>"), F.lit(""))
    bare = line.rlike("[0-9]") & (F.size(own) < MIN_TOKENS) & (~rest.rlike(r"\p{L}") | (F.octet_length(line) - F.octet_length(rest) > HIDDEN))
    return F.when(bare, own).otherwise(tokens)


def lines_with_keys(docs: DataFrame, min_tokens: int = MIN_TOKENS, leading: int = LEADING, runs: int = RUNS) -> DataFrame:
    """doc_id, line (position from 0), key: one row per template key of each line that counts.

    A line's keys are the hash of its full template and those of the template with one run of positions left open, all
    under the tree's path. Each run is hashed once, in a column of its own.
    """
    lines = docs.filter("doc_id is not null").select("doc_id", F.posexplode(F.split("text", "\n")).alias("line", "_text"))
    lines = lines.filter((F.octet_length("_text") >= 2 * min_tokens - 1) & F.col("_text").rlike(r"[^\x20\x09-\x0D]")).select("doc_id", "line", tokens_of(F.col("_text")).alias("_t"))
    n = F.size("_t")
    # Run r covers positions from edge r up to edge r + 1 behind the leading tokens; slices count from 1.
    edge = [F.lit(leading + 1) + F.floor(F.greatest(n - leading, F.lit(0)) * r / runs).cast("int") for r in range(runs + 1)]
    piece = [F.xxhash64(F.lit(r), F.slice("_t", edge[r], edge[r + 1] - edge[r])).alias(f"_p{r}") for r in range(runs)]
    lines = lines.select("doc_id", "line", F.when(n >= min_tokens, F.struct((n >= leading + runs).alias("_open"), F.xxhash64(n, F.slice("_t", 1, leading)).alias("_path"), *piece)).alias("_k"))
    hashed = [F.xxhash64(F.lit(runs), "_k._path", *(f"_k._p{r}" for r in range(runs)))]
    hashed += [F.xxhash64(F.lit(r), "_k._path", *(f"_k._p{k}" for k in range(runs) if k != r)) for r in range(runs)]
    return lines.select("doc_id", "line", F.explode(F.when(F.col("_k._open"), F.array(*hashed)).when(F.col("_k").isNotNull(), F.array(hashed[0]))).alias("key"))


def dropped_lines(docs: DataFrame, min_tokens: int = MIN_TOKENS) -> DataFrame:
    """doc_id, lines: positions to drop, for documents that lose any."""
    keep = Scratch(docs.sparkSession)
    keys = keep(lines_with_keys(docs, min_tokens), "template-keys")
    recurring = keys.groupBy("key").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).filter("first < last").select("key", "first")
    recurring = keep(recurring, "recurring-templates")
    hit = keys.join(recurring.hint("merge"), "key").filter("doc_id > first")
    return keep.result(hit.groupBy("doc_id").agg(F.collect_set("line").alias("lines")), "dropped-lines")


def dedup_lines(docs: DataFrame, min_tokens: int = MIN_TOKENS) -> DataFrame:
    """``docs`` with the text less its dropped lines, and ``dropped_lines``, the number dropped."""
    gone = dropped_lines(docs.select("doc_id", "text"), min_tokens).withColumnRenamed("doc_id", "__chartrel_id").withColumnRenamed("lines", "__chartrel_gone")
    names = [c for c in docs.columns if c != "dropped_lines"]
    full = docs.join(gone.hint("merge"), F.col("doc_id") == F.col("__chartrel_id"), "left")  # what goes grows with the texts: one plan at every size
    full = full.withColumn("__chartrel_lines", F.when(F.col("__chartrel_gone").isNotNull(), F.split("text", "\n")))
    left = F.array_except(F.sequence(F.lit(0), F.size("__chartrel_lines") - 1), "__chartrel_gone")  # a set difference: linear in the lines
    full = full.withColumn("__chartrel_left", F.when(F.col("__chartrel_lines").isNotNull(), left))
    kept = F.array_join(F.transform("__chartrel_left", lambda i: F.get("__chartrel_lines", i)), "\n")
    return full.select(
        *(F.when(F.col("__chartrel_left").isNull(), F.col("text")).otherwise(kept).alias(c) if c == "text" else F.col(f"`{c}`") for c in names),
        F.when(F.col("__chartrel_left").isNull(), 0).otherwise(F.size("__chartrel_lines") - F.size("__chartrel_left")).cast("long").alias("dropped_lines"))
