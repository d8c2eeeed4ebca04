"""Benchmark decontamination by SimHash of item-sized windows, in DataFrame operations only.

Texts and items are lower-cased words. An item-sized window of similarity above zero holds one of the item's shingles word for word,
so a window is laid wherever a text has such a shingle, shifted so that it stands where the item has it: no window that
could count is left out, and nothing else is asked of a window before its fingerprint. Window and item get a 64-bit
SimHash of their weighted runs of two words, which an edited word changes less than longer runs. A multi-index finds all
items within RADIUS bits: fingerprints are cut into four blocks of 16 bits, and as two within the radius differ in at
most two bits of some block, each block of an item is stored with all values up to two bits away and looked up by
equality. Of unrelated fingerprints 0.8 % meet. What meets within the radius is verified by the exact weighted Jaccard
similarity of five-word shingles. Two windows of that similarity or more differ in 6 bits on average; README gives
the measured recall.

Defined results: null and empty texts and items match nothing, nor does a null id. Items of fewer words than a shingle are matched by
their whole length. Ties are all reported. Rows of one id are one document: every one of its texts is searched and the
best window counts. Of several texts of one item id the least counts. Item tables are broadcast only after their number
of rows is checked; beyond the bound the same joins are shuffled. Other columns are ignored by ``matches`` and pass
through ``decontaminate``.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, stored

SHINGLE, PAIR, SIMILARITY, BITS = 5, 2, 0.8, 64
#: Blocks of a fingerprint and bits that a block may differ by: a radius of BLOCKS * (NEAR + 1) - 1 bits is guaranteed.
BLOCKS, NEAR = 4, 2
RADIUS = BLOCKS * (NEAR + 1) - 1
#: Rows of a table of items (some 40 bytes each), and candidate documents, that may be broadcast.
BROADCAST_ROWS, BROADCAST_IDS = 1_000_000, 1_000_000
_RESULT = "doc_id long, item_id long, position int, similarity double"


def words_of(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def shingles(words: Column, width: int) -> Column:
    """Hash of every run of ``width`` words; none where there are fewer words."""
    hashes = F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.size(words) - width)), lambda i: F.xxhash64(*(F.get(words, i + k) for k in range(width))))
    return F.when(F.size(words) >= width, hashes).otherwise(F.array().cast("array<bigint>"))


def by_width(words: Column, width: Column, widths: list[int]) -> Column:
    """Shingles of the width that each row names."""
    out = F.array().cast("array<bigint>")
    for k in widths:
        out = F.when(width == k, shingles(words, k)).otherwise(out)
    return out


def fingerprints(rows: DataFrame, by: list[str]) -> DataFrame:
    """by, print (BITS bits): sign of the weighted sum per bit of hashed runs; rows hold by, h, w."""
    spread = F.xxhash64(F.lit(77), F.col("h"))
    bits = [F.sum(F.when(F.shiftright(spread, b).bitwiseAND(1) == 1, F.col("w")).otherwise(-F.col("w"))) for b in range(BITS)]
    sums = rows.groupBy(*by).agg(*(s.alias(f"_b{b}") for b, s in enumerate(bits)))
    sign = None
    for b in range(BITS):
        bit = F.when(F.col(f"_b{b}") > 0, F.lit(1 << b if b < 63 else -(1 << 63))).otherwise(F.lit(0))
        sign = bit if sign is None else sign.bitwiseOR(bit)
    return sums.select(*by, sign.alias("print"))


def blocks(print_: Column) -> Column:
    """(block, value) of the runs of bits that make up the fingerprint."""
    size = BITS // BLOCKS
    return F.array(*(F.struct(F.lit(k).alias("block"), F.shiftrightunsigned(print_, k * size).bitwiseAND((1 << size) - 1).cast("int").alias("value")) for k in range(BLOCKS)))


def flips(near: int = NEAR) -> list[int]:
    """All changes of up to ``near`` bits of a block."""
    return [sum(1 << b for b in bits) for n in range(near + 1) for bits in combinations(range(BITS // BLOCKS), n)]


def near_prints(left: DataFrame, right: DataFrame, on: list[str], small=lambda df: df) -> DataFrame:
    """Pairs of rows of equal ``on`` whose fingerprints ``print`` and ``print2`` differ in RADIUS bits at most; each once per block that they meet in."""
    asked = left.withColumn("_b", F.explode(blocks(F.col("print"))))
    values = right.withColumn("_b", F.explode(blocks(F.col("print2"))))
    around = F.transform(F.array(*map(F.lit, flips())), lambda x: F.struct(F.col("_b.block").alias("block"), F.col("_b.value").bitwiseXOR(x).alias("value")))
    kept = values.withColumn("_b", F.explode(around))
    return asked.join(small(kept), [*on, "_b"]).filter(F.bit_count(F.col("print").bitwiseXOR(F.col("print2"))) <= RADIUS).drop("_b")


def _weights(grams: DataFrame, total: int) -> DataFrame:
    """width, h, weight: inverse document frequency over the items; ``grams`` holds item_id, width, h."""
    return grams.groupBy("width", "h").agg(F.count_distinct("item_id").alias("_df")).select("width", "h", (1 + F.log(F.lit(float(total)) / F.col("_df"))).alias("weight"))


def matches(docs: DataFrame, items: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, item_id, position (first word of the best window, from 0), similarity: one row per document and item that match."""
    spark = docs.sparkSession
    keep = Scratch(spark)
    item = items.filter("item_id is not null and text is not null").groupBy("item_id").agg(F.min("text").alias("text")).select("item_id", words_of(F.col("text")).alias("_w")).filter(F.size("_w") > 0)
    item = keep(item.withColumn("length", F.size("_w")).withColumn("width", F.least(F.lit(SHINGLE), F.size("_w"))).withColumn("pair", F.least(F.lit(PAIR), F.size("_w"))), "items")
    total = item.count()
    if not total:
        return keep.result(spark.createDataFrame([], _RESULT), "leaks")
    widths = sorted(r["width"] for r in item.select("width").distinct().collect())  # five values at most
    rare = F.lit(1.0) + F.log(F.lit(float(total)))  # weight of runs that no item has
    grams = keep(item.select("item_id", "length", "width", F.posexplode(by_width(F.col("_w"), F.col("width"), widths)).alias("at", "h")), "item-shingles")
    few = grams.count() <= BROADCAST_ROWS
    small = (lambda df: F.broadcast(df)) if few else (lambda df: df)
    # One pass over the texts: every shingle, of every width that an item has, that some item has.
    texts = docs.filter("doc_id is not null and text is not null").select("doc_id", F.xxhash64("text").alias("copy"), words_of(F.col("text")).alias("_w"))
    here = texts.select("doc_id", "copy", F.size("_w").alias("n"), F.posexplode(F.concat(*(shingles(F.col("_w"), k) for k in widths))).alias("_p", "h"))
    laid = here.join(small(grams.select("width", "h", "length", "at")), "h")
    ahead, before = {}, F.lit(0)  # shingles of lesser widths stand before those of a width
    for k in widths:
        ahead[k], before = before, before + F.greatest(F.lit(0), F.col("n") - k + 1)
    offset = F.coalesce(*(F.when(F.col("width") == k, ahead[k]) for k in widths))
    laid = laid.withColumn("pos", F.col("_p") - offset).filter((F.col("pos") >= 0) & (F.col("pos") <= F.col("n") - F.col("width")))
    laid = laid.select("doc_id", "copy", "width", "length", F.greatest(F.lit(0), F.least(F.col("pos") - F.col("at"), F.col("n") - F.col("length"))).alias("start")).distinct()
    laid = keep(laid, "window-places")
    ids = laid.select("doc_id").distinct()
    near = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids.hint("merge")
    found = docs.filter("text is not null").select("doc_id", "text").join(near, "doc_id").select("doc_id", F.xxhash64("text").alias("copy"), "text").dropDuplicates(["doc_id", "copy"])
    key = ["doc_id", "copy", "width", "length", "start"]
    window = laid.join(found, ["doc_id", "copy"]).select(*key, F.least(F.lit(PAIR), F.col("width")).alias("pair"), F.slice(words_of(F.col("text")), F.col("start") + 1, F.col("length")).alias("_w"))
    window = keep(window, "windows")

    def printed(rows: DataFrame, by: list[str], known: DataFrame) -> DataFrame:
        runs = rows.select(*by, F.col("pair").alias("_p"), F.explode(by_width(F.col("_w"), F.col("pair"), [1, PAIR])).alias("h"))
        return fingerprints(runs.join(small(known.withColumnRenamed("width", "_p")), ["_p", "h"], "left").withColumn("w", F.coalesce("weight", rare)), by)

    known = keep(_weights(item.select("item_id", F.col("pair").alias("width"), F.explode(by_width(F.col("_w"), F.col("pair"), [1, PAIR])).alias("h")), total), "pair-weights")
    right = printed(item, ["item_id", "length"], known).withColumnRenamed("print", "print2")
    tables = (lambda df: F.broadcast(df)) if total * BLOCKS * len(flips()) <= BROADCAST_ROWS else (lambda df: df)
    pairs = keep(near_prints(printed(window, key, known), keep(right, "item-prints"), ["length"], tables).select(*key, "item_id").distinct(), "window-candidates")
    # The exact similarity of what met.
    weight = keep(_weights(grams.select("item_id", "width", "h"), total), "shingle-weights")
    weighed = keep(grams.groupBy("item_id", "width", "h").agg(F.count("*").alias("tf")).join(small(weight), ["width", "h"]).select("item_id", "h", (F.col("tf") * F.col("weight")).alias("v")), "item-weights")
    whole = weighed.groupBy("item_id").agg(F.sum("v").alias("it"))
    counted = window.join(pairs.select(*key).distinct(), key, "left_semi").select(*key, F.explode(by_width(F.col("_w"), F.col("width"), widths)).alias("h")).groupBy(*key, "h").agg(F.count("*").alias("tf"))
    counted = keep(counted.join(small(weight), ["width", "h"], "left").select(*key, "h", (F.col("tf") * F.coalesce("weight", rare)).alias("w")), "window-shingles")
    size = counted.groupBy(*key).agg(F.sum("w").alias("wt"))
    shared = pairs.join(counted, key).join(small(weighed), ["item_id", "h"]).groupBy(*key, "item_id").agg(F.sum(F.least("w", "v")).alias("both"))
    met = shared.join(size, key).join(small(whole), "item_id").withColumn("similarity", F.col("both") / (F.col("wt") + F.col("it") - F.col("both"))).filter(F.col("similarity") >= similarity - 1e-9)
    best = met.groupBy("doc_id", "item_id").agg(F.max(F.struct("similarity", (-F.col("start")).alias("s"))).alias("best"))
    return keep.result(best.select("doc_id", "item_id", (-F.col("best.s")).cast("int").alias("position"), F.round("best.similarity", 9).alias("similarity")), "leaks")


def decontaminate(docs: DataFrame, items: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """``docs`` without the documents that hold a benchmark item."""
    leaks = stored(matches(docs.select("doc_id", "text"), items, similarity).select(F.col("doc_id").alias("__chartrel_leak")).distinct(), "leak-ids")
    few = F.broadcast(leaks) if leaks.count() <= BROADCAST_IDS else leaks
    return docs.join(few, F.col("doc_id") == F.col("__chartrel_leak"), "left_anti")
