"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Documents are cut into word blocks. Each source gets an exact quota of blocks, whole epochs first and then the front of
one more permutation. The quota vector is split from the root of a binary tree down to output shards, each split one
multivariate-hypergeometric draw seeded by the node, so any executor can recompute any path and none needs the whole
tree. Position p of a source's permuted sequence thus belongs to exactly one shard; within a shard blocks are put in
hashed order. What a document gives to the mix is read from the blocks that the tree has dealt.

A block's place in its source's permutation is its rank by a hash of source, id, text and block. Ranks come from buckets
of some hundred blocks by the leading bits of that hash: totals of buckets are added up within groups of buckets, totals of
groups within the source, and both are joined back, so no task sorts more than a bucket and the driver sees sources only.

Defined results: a null text has size 0, is never drawn and is returned with taken 0. A null source is a source of its
own, last in order. Repeated ids are separate documents, each with its own row in the result; rows that are equal
throughout are counted first and numbered, so reruns agree on any partitioning. An empty table gives an empty mix. Extra
columns are ignored. The number of sources is taken to fit the driver, as their targets depend on each other.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, Scratch, parts, stored

#: What names a document: its id may repeat, rows equal in all of these are numbered by ``twin``.
DOCUMENT = ["doc_id", "code", "size", "digest", "twin"]
LAYOUT = "doc_id long, code int, size long, digest long, twin long, block int, words long, epoch int, shard long, place long"
#: Sources whose table is broadcast; more are joined by a shuffle.
BROADCAST_SOURCES = 100_000
#: Words of a block, blocks of an output shard, blocks of a bucket of ranks, buckets whose totals are added up together (a power of two).
BLOCK_WORDS, SHARD_BLOCKS, BUCKET_BLOCKS, GROUP = 128, 4096, 256, 1024


def sized(docs: DataFrame) -> DataFrame:
    """doc_id, source, size (the number of words of the whole text) and digest of the text."""
    return docs.select("doc_id", "source", F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"), F.xxhash64("text").alias("digest"))


def targets(sizes: dict, weights=(1, 2, 3), cap: float = 3.0) -> dict:
    """Share of all words per source: by repeating weights in code-point order, null last, held at ``cap`` times the source."""
    names = sorted(sizes, key=lambda s: (s is None, (s or "").encode("utf-32-be")))
    weight = {s: float(weights[i % len(weights)]) for i, s in enumerate(names)}
    left, free, out = float(sum(sizes.values())), list(names), {}
    while free:
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = [s for s in free if share[s] > cap * sizes[s]]
        if not over:
            return out | share
        for s in over:
            out[s] = cap * sizes[s]
            left -= out[s]
        free = [s for s in free if s not in over]
    return out


#: Nodes of the tree that a task remembers.
KEPT = 100_000


class SplittingTree:
    """Quotas of one node's shards, split on demand; equal seeds give equal trees everywhere."""

    def __init__(self, quotas: list[int], shards: int, seed: int):
        self.shards, self.seed, self.root = shards, seed, np.array(quotas, dtype=np.int64)
        self.nodes: dict[tuple[int, int], np.ndarray] = {}  # left halves

    def _draw(self, rng, good: int, bad: int, take: int) -> int:
        if good + bad < 1_000_000_000:
            return int(rng.hypergeometric(good, bad, take)) if good and take else 0
        share = good / (good + bad)  # beyond the sampler's range: its normal limit, held to what is possible
        sd = math.sqrt(take * share * (1 - share) * (good + bad - take) / max(1, good + bad - 1))
        return int(min(good, take, max(0, take - bad, round(rng.normal(take * share, sd)))))

    def halves(self, lo: int, hi: int, quota: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """Quota vectors left and right of the middle of shards [lo, hi), whose own vector is ``quota``."""
        mid = (lo + hi) // 2
        if (lo, mid) not in self.nodes:
            if len(self.nodes) > KEPT:  # nodes are drawn again when needed
                self.nodes = {}
            rng, total = np.random.default_rng((self.seed, lo, hi)), int(quota.sum())
            take, left = total * (mid - lo) // (hi - lo), np.zeros_like(quota)
            for i, n in enumerate(quota.tolist()):
                left[i] = self._draw(rng, n, total - n, take)
                total, take = total - n, take - int(left[i])
            self.nodes[lo, mid] = left
        left = self.nodes[lo, mid]
        return left, quota - left, mid

    def runs(self, source: int, first: int, last: int) -> Iterator[tuple[int, int, int]]:
        """(shard, from, to) covering positions [first, last) of a source's sequence."""
        todo = [(0, self.shards, 0, self.root)]
        while todo:
            lo, hi, at, quota = todo.pop()
            n = int(quota[source])
            if at >= last or at + n <= first or not n:
                continue
            if hi - lo == 1:
                yield lo, max(at, first), min(at + n, last)
                continue
            left, right, mid = self.halves(lo, hi, quota)
            todo += [(mid, hi, at + int(left[source]), right), (lo, mid, at, left)]


def _assigner(total: list[int], quotas: list[int], shards: int, seed: int):
    names = [c.split()[0] for c in LAYOUT.split(", ")]

    def assign(batches):
        tree = SplittingTree(quotas, shards, seed)
        for batch in batches:
            rank, code = batch.column("rank").to_numpy(), batch.column("code").to_numpy()
            rows, epochs, shard = [], [], []
            for s in np.unique(code).tolist():
                mine = np.flatnonzero(code == s)
                mine = mine[np.argsort(rank[mine], kind="stable")]
                n, quota = total[s], quotas[s]
                for epoch in range(-(-quota // n) if n else 0):
                    at = rank[mine] + epoch * n
                    hit = at < quota
                    at, where = at[hit], np.full(int(hit.sum()), -1, dtype=np.int64)
                    if len(at):
                        for k, lo, hi in tree.runs(s, int(at[0]), int(at[-1]) + 1):
                            a, b = np.searchsorted(at, (lo, hi))
                            where[a:b] = k
                    if (where < 0).any():
                        raise AssertionError("a drawn position belongs to no shard")
                    rows.append(mine[hit])
                    epochs.append(np.full(len(at), epoch, dtype=np.int32))
                    shard.append(where)
            if rows:
                out = batch.take(pa.array(np.concatenate(rows)))
                more = {"epoch": pa.array(np.concatenate(epochs)), "shard": pa.array(np.concatenate(shard))}
                yield pa.RecordBatch.from_arrays([more[c] if c in more else out.column(c) for c in names], names=names)

    return assign


def _small(spark, rows: list[tuple], schema: str) -> DataFrame:
    """A table of one row per source, from the driver."""
    df = spark.createDataFrame(rows, schema)
    return F.broadcast(df) if len(rows) <= BROADCAST_SOURCES else df


def _ranked(blocks: DataFrame, bits: DataFrame, seed: int, keep: Scratch) -> DataFrame:
    """``blocks`` (DOCUMENT, block, words, draw) with rank and ``upto``, the words up to the block's end, in its source's permutation."""
    top = F.shiftrightunsigned("draw", 1).cast("long")  # 63 bits, never negative: buckets are its leading ones, so they lie in order
    blocks = blocks.join(bits, "code").withColumn("bucket", F.floor(top / F.pow(F.lit(2.0), F.lit(63) - F.col("bits"))).cast("long")).drop("bits")
    blocks = keep(blocks, "mix-blocks")
    sums = keep(blocks.groupBy("code", "bucket").agg(F.count("*").alias("n"), F.sum("words").alias("w")).withColumn("group", F.floor(F.col("bucket") / GROUP)), "bucket-totals")
    before = lambda by, order, c: F.coalesce(F.sum(c).over(Window.partitionBy(*by).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    groups = sums.groupBy("code", "group").agg(F.sum("n").alias("n"), F.sum("w").alias("w"))
    groups = groups.select("code", "group", before(["code"], "group", "n").alias("n1"), before(["code"], "group", "w").alias("w1"))
    inner = sums.select("code", "bucket", "group", before(["code", "group"], "bucket", "n").alias("n2"), before(["code", "group"], "bucket", "w").alias("w2"))
    starts = keep(inner.join(groups, ["code", "group"]).select("code", "bucket", (F.col("n1") + F.col("n2")).alias("n0"), (F.col("w1") + F.col("w2")).alias("w0")), "bucket-starts")
    inside = Window.partitionBy("code", "bucket").orderBy(F.shiftrightunsigned("draw", 1), "draw", "doc_id", "size", "digest", "twin", "block")
    ranked = blocks.withColumn("i", F.row_number().over(inside)).withColumn("own", F.sum("words").over(inside.rowsBetween(Window.unboundedPreceding, 0)))
    return ranked.join(starts.hint("merge"), ["code", "bucket"]).select(*DOCUMENT, "block", "words", (F.col("n0") + F.col("i") - 1).alias("rank"), (F.col("w0") + F.col("own")).alias("upto"), F.xxhash64(F.lit(seed + 1), "draw").alias("place"))


def mix_sources(sizes: DataFrame, *, weights=(1, 2, 3), cap: float = 3.0, block_words: int = BLOCK_WORDS, blocks_per_shard: int = SHARD_BLOCKS, blocks_per_bucket: int = BUCKET_BLOCKS, seed: int = 7) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Layout of the mix (one row per drawn block copy), the numbered documents it is of, and code, source, source_size and target by source.

    ``sizes``: doc_id, source, size, and digest where ids may repeat with different texts.
    """
    spark = sizes.sparkSession
    keep = Scratch(spark)
    sizes = sizes if "digest" in sizes.columns else sizes.withColumn("digest", F.lit(0).cast("long"))
    counted = keep(sizes.groupBy("doc_id", "source", "size", "digest").agg(F.count("*").alias("_n")), "mix-rows")
    each = counted.withColumn("_k", F.explode(F.sequence(F.lit(0), F.floor((F.col("_n") - 1) / 1000).cast("long"))))  # thousands first: no long list in one row
    each = each.withColumn("twin", F.explode(F.sequence(F.col("_k") * 1000, F.least(F.col("_k") * 1000 + 999, F.col("_n") - 1)))).drop("_n", "_k")
    per = {r["source"]: (r["words"], r["blocks"]) for r in counted.groupBy("source").agg(F.sum(F.col("size") * F.col("_n")).cast("long").alias("words"), F.sum(F.ceil(F.col("size") / block_words) * F.col("_n")).cast("long").alias("blocks")).collect()}
    names = sorted(per, key=lambda s: (s is None, (s or "").encode("utf-32-be")))
    words, target = {s: per[s][0] for s in names}, targets({s: per[s][0] for s in names}, weights, cap)
    total = [per[s][1] for s in names]
    by_source = _small(spark, [(i, s, words[s], float(target[s])) for i, s in enumerate(names)], "code int, source string, source_size long, target double")
    bits = _small(spark, [(i, float(max(0, math.ceil(math.log2(max(1, n) / blocks_per_bucket))))) for i, n in enumerate(total)], "code int, bits double")
    code = by_source.select("code", F.col("source").alias("_s"))
    held = stored(each.join(code, each.source.eqNullSafe(F.col("_s"))).select(*DOCUMENT), "mix-documents")
    blocks = held.filter("size > 0").select(*DOCUMENT, F.explode(F.sequence(F.lit(0), F.ceil(F.col("size") / block_words).cast("int") - 1)).alias("block"))
    blocks = blocks.select(*DOCUMENT, "block", F.least(F.lit(block_words), F.col("size") - F.col("block") * block_words).cast("long").alias("words"), F.xxhash64(F.lit(seed), *DOCUMENT, "block").alias("draw"))
    ranked = keep(_ranked(blocks, bits, seed, keep), "mix-ranks")
    rest = [target[s] - int(target[s] // w) * w if w else 0.0 for s, w in words.items()]
    cuts = _small(spark, [(i, float(r)) for i, r in enumerate(rest)], "code int, rest double")
    fronts = {r["code"]: r["n"] for r in ranked.join(cuts, "code").filter(F.col("upto") - F.col("words") / 2 <= F.col("rest")).groupBy("code").agg(F.count("*").alias("n")).collect()}
    quotas = [min(int(cap) * n, int(target[s] // words[s]) * n + (fronts.get(i, 0) if rest[i] > 0 else 0)) if words[s] else 0 for i, (s, n) in enumerate(zip(names, total))]
    shards = max(1, -(-sum(quotas) // blocks_per_shard))
    layout = ranked.select(*DOCUMENT, "block", "words", "rank", "place").mapInArrow(_assigner(total, quotas, shards, seed), LAYOUT)
    return keep.result(layout, "mix-layout"), held, by_source


def taken_by_document(layout: DataFrame, held: DataFrame, by_source: DataFrame) -> DataFrame:
    """doc_id, size, source_size, target, taken, shards (of every drawn block copy, sorted) and source for every document."""
    every = held.select(*DOCUMENT, F.lit(0).cast("long").alias("words"), F.lit(None).cast("long").alias("shard")).unionByName(layout.select(*DOCUMENT, "words", "shard"))
    drawn = every.groupBy(*DOCUMENT).agg(F.sum("words").cast("long").alias("taken"), F.sort_array(F.collect_list("shard")).alias("shards"))  # a document's own blocks
    return drawn.join(by_source, "code").select("doc_id", "size", "source_size", "target", "taken", "shards", "source")


def shuffled_mix(docs: DataFrame, layout: DataFrame, by_source: DataFrame, block_words: int = BLOCK_WORDS) -> DataFrame:
    """shard, place, epoch, doc_id, twin, block, text: the words of every drawn block, dealt by shard and in hashed order inside each.

    This is what a writer of training files reads. Blank runs inside a block become one blank.
    """
    name = [F.xxhash64(F.lit(k), "doc_id", "source", "digest").alias(f"_n{k}") for k in (1, 2)]  # 128 bits, never null
    own = docs.filter("text is not null").select("doc_id", "source", F.xxhash64("text").alias("digest"), F.regexp_extract_all("text", F.lit(f"({WORD})")).alias("_w")).filter(F.size("_w") > 0)
    # Words are cut once per text, blocks travel on their own: a long text is no task of its own.
    last = F.floor((F.size("_w") - 1) / block_words).cast("int")
    cut = F.transform(F.sequence(F.lit(0), last), lambda i: F.array_join(F.slice("_w", i * block_words + 1, F.lit(block_words)), " "))
    own = own.select(*name, F.posexplode(cut).alias("block", "text")).dropDuplicates(["_n1", "_n2", "block"])
    wanted = layout.join(by_source.select("code", "source"), "code").select(*name, "doc_id", "twin", "block", "epoch", "shard", "place")
    met = wanted.join(own, ["_n1", "_n2", "block"]).select("shard", "place", "epoch", "doc_id", "twin", "block", "text")
    return met.repartition(parts(docs.sparkSession), "shard").sortWithinPartitions("shard", "place", "epoch", "doc_id", "twin", "block")
