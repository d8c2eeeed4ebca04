"""Near-dedup by improved consistent weighted sampling over TF-IDF shingles, banded, verified by weighted Jaccard.

Words are blank-delimited, their ASCII letters lower-cased; shingles are five words in a row (all words of a shorter text). A shingle
weighs its count in the text times an inverse document frequency that saturates: every shingle in less than one document
of a thousand has the same, highest one. So only the widespread shingles need exact counts: a pass over all texts adds
their shingles up in a fixed number of buckets, and a second pass counts, over all texts, exactly the shingles of those
buckets that reach the bound. What is broadcast is thereby limited by the shingles of a mean text times a thousand.

Each signature entry is a consistent weighted sample: random variates come from tables indexed by fourteen bits of the
shingle's hash, ties within a table row fall to the rest of the hash. Equal texts are one class beforehand. Bands of four
entries make buckets; in each bucket members are compared with one leader, then, as long as a bucket still holds several
classes, with members of its largest class, and what remains is compared in full, so of the texts that share a bucket no link is
lost and no crowd is compared all against all while leaders explain it. Two texts of similarity s share a bucket with
probability 1 - (1 - s^4)^12 (0.998 at 0.8, the least similarity that links); README has the measured recall.

Defined results: texts without words are linked with equal texts only; a null text is linked with nothing. A null id has
a null class and is kept. Rows of one id are one document; of several texts under an id all have buckets, and the least is what candidates are verified with. Extra columns pass through ``dedup``.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, arrow_rows, mix, sliced, slices, stored, text_batches
from .components import components

WIDTH, SIMILARITY = 5, 0.8
BANDS, ROWS = 12, 4
ENTRIES = BANDS * ROWS
#: Document share below which the inverse document frequency no longer grows; buckets of the first pass, in ranges.
SHARE, BUCKETS, RANGES = 1e-3, 1 << 22, 64
#: Tables of counts that one group adds up.
MERGED = 64
SLOTS = 1 << 14
ROUNDS = 8
#: Pairs per distinct text up to which the open buckets are compared in full at once.
PAIRS_PER_TEXT = 100
#: Pairs of a bucket beyond which it is compared in blocks of so many texts; shingles that a verifier keeps.
BLOCK_PAIRS, BLOCK, CACHED = 2000, 256, 2_000_000
#: Bytes of text that are hashed at once.
PIECE = 1 << 18
#: Pairs of whole texts that are brought to Python at once; bytes up to which a task does not trim its memory.
PAIR_ROWS, TRIM = 256, 1 << 22
#: Links up to which classes are found on the driver (2 MB); beyond, by joins.
FEW_LINKS = 1 << 17


_rng = np.random.default_rng(29)
_BYTE = _rng.integers(1, 1 << 64, 256, np.uint64) | np.uint64(1)
_BYTE[65:91] = _BYTE[97:123]  # ASCII letters are lower-cased
_PLACE = _rng.integers(1, 1 << 64, 256, np.uint64) | np.uint64(1)
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True


def _word_hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and first byte of every blank-delimited word of UTF-8 bytes."""
    ink = ~_BLANK[data]
    edge = np.flatnonzero(np.diff(np.concatenate(([False], ink, [False]))))
    start, end = edge[::2], edge[1::2]
    if not len(start):
        return np.zeros(0, np.uint64), start
    first = np.concatenate(([0], start))
    place = np.arange(len(data)) - np.repeat(first, np.diff(np.append(first, len(data))))
    with np.errstate(over="ignore"):
        v = _BYTE[data] * _PLACE[place & 255]
        if place.max() > 255:  # beyond the table a long word's places get numbers of their own
            far = place > 255
            v[far] += mix(place[far])
        v[~ink] = 0
        return mix(np.add.reduceat(v, start)), start


def shingled(data: np.ndarray, offsets: np.ndarray, distinct: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text number, 48-bit hash and count of the shingles of texts laid end to end, by text and hash.

    Not ``distinct``: every occurrence in the order of the texts, counted once. At most 65536 texts at a time.
    """
    got = []
    lo = int(offsets[0])
    while lo < offsets[-1]:  # bounded pieces, cut behind a blank
        hi = min(int(offsets[-1]), lo + PIECE)
        if hi < offsets[-1]:
            gap = np.flatnonzero(_BLANK[data[lo:hi]])
            ends = offsets[(offsets > lo) & (offsets <= hi)]
            cut = max(lo + int(gap[-1]) + 1 if len(gap) else lo, int(ends[-1]) if len(ends) else lo)
            hi = cut if cut > lo else int(offsets[-1])
        got.append((lo, hi))
        lo = hi
    x, at = [], []
    for lo, hi in got:
        part = data[lo:hi]
        inner = offsets[(offsets > lo) & (offsets < hi)] - lo
        if len(inner):  # a blank between texts keeps their words apart
            part = np.insert(part, inner, 32)
        h, start = _word_hashes(part)
        x.append(h)
        at.append(start - np.searchsorted(inner + np.arange(len(inner)), start, side="left") + lo if len(inner) else start + lo)
    none = np.zeros(0, np.int64)
    x, at = (np.concatenate(x), np.concatenate(at)) if x else (np.zeros(0, np.uint64), none)
    if not len(x):
        return none, np.zeros(0, np.uint64), none
    size = np.diff(np.searchsorted(at, offsets))
    text = np.repeat(np.arange(len(size)), size)
    left = np.repeat(np.cumsum(size), size) - np.arange(len(x))
    with np.errstate(over="ignore"):
        h = np.zeros(len(x), np.uint64)
        for j in range(WIDTH):
            h *= np.uint64(0x9DDFEA08EB382D69)
            h[: max(0, len(x) - j)] += x[j:]
        short = np.flatnonzero((left < WIDTH) & (np.repeat(size, size) == left))  # the whole of a text with fewer words
        for i in short.tolist():
            v = np.uint64(left[i])
            for j in range(int(left[i])):
                v = v * np.uint64(0x9DDFEA08EB382D69) + x[i + j]
            h[i] = v
        use = left >= WIDTH
        use[short] = True
        h, text = mix(h[use]) >> np.uint64(16), text[use]
    if not distinct:
        return text, h, np.ones(len(h), np.int64)
    key = np.sort((text.astype(np.uint64) << np.uint64(48)) | h)
    first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
    key = key[first]
    return (key >> np.uint64(48)).astype(np.int64), key & np.uint64((1 << 48) - 1), np.diff(np.append(first, len(h)))


def encoded(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of texts."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    return np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)])


def _chunks(batch) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of a batch's texts as bytes and offsets, straight from Arrow's buffers; nulls are empty."""
    column = batch.column("text").cast(pa.large_string())
    _, ends, body = column.buffers()
    offsets = np.frombuffer(ends, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    data = np.frombuffer(body, np.uint8) if body is not None else np.zeros(0, np.uint8)
    for a, b in slices(np.diff(offsets).tolist(), PIECE):
        yield a, b, data, offsets[a : b + 1]


def _bucket_counts(batches):
    total = np.zeros(BUCKETS, np.int32)
    for batch in sliced(batches, 4096, TRIM):
        for _, _, data, offsets in _chunks(batch):
            _, h, _ = shingled(data, offsets, distinct=False)
            at, n = np.unique((h >> np.uint64(26)).astype(np.int32), return_counts=True)
            total[at] += n.astype(np.int32)
    step, salt = BUCKETS // RANGES, zlib.crc32(total.tobytes()) >> 1
    full = [r for r in range(RANGES) if total[r * step : (r + 1) * step].any()]
    yield pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array([salt] * len(full), pa.int32()), pa.array([zlib.compress(total[r * step : (r + 1) * step].astype(np.int64).tobytes(), 1) for r in full], pa.binary())], names=["range", "salt", "counts"])


def _added(table: pa.Table) -> pa.Table:
    total = sum(np.frombuffer(zlib.decompress(c.as_py()), np.int64) for c in table.column("counts"))
    return pa.table({"range": pa.array([table.column("range")[0].as_py()], pa.int32()), "salt": pa.array([table.column("salt")[0].as_py()], pa.int32()), "counts": pa.array([zlib.compress(total.tobytes(), 1)], pa.binary())})


def _heavy(least: int):
    def run(batches):
        for batch in batches:
            for r, c in zip(batch.column("range").to_pylist(), batch.column("counts").to_pylist()):
                at = np.flatnonzero(np.frombuffer(zlib.decompress(c), np.int64) >= least)
                yield pa.RecordBatch.from_arrays([pa.array(at + r * (BUCKETS // RANGES), pa.int64())], names=["bucket"])

    return run


def _candidates(shared):
    def run(batches):
        mask = np.zeros(BUCKETS, bool)
        mask[shared.value] = True
        for batch in sliced(batches, 4096, TRIM):
            found = [np.zeros(0, np.uint64)]
            for _, _, data, offsets in _chunks(batch):
                text, h, _ = shingled(data, offsets, distinct=False)
                hit = mask[(h >> np.uint64(26)).astype(np.int64)]
                found.append(np.unique((text[hit].astype(np.uint64) << np.uint64(48)) | h[hit]) & np.uint64((1 << 48) - 1))
            h, n = np.unique(np.concatenate(found), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(n.astype(np.int64))], names=["h", "n"])

    return run


class Weights:
    """Inverse document frequencies: of the widespread shingles by sorted hash, and the saturated one of all others."""

    def __init__(self, keys: np.ndarray, df: np.ndarray, documents: int, least: int):
        order = np.argsort(keys)
        self.keys = keys[order]
        self.idf = (1 + np.log((1 + documents) / (1 + df[order]))).astype(np.float64)
        self.most = float(1 + np.log((1 + documents) / (1 + least)))

    def of(self, h: np.ndarray) -> np.ndarray:
        out = np.full(len(h), self.most)
        if len(self.keys) and len(h):
            at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
            hit = self.keys[at] == h
            out[hit] = self.idf[at[hit]]
        return out


def weights(docs: DataFrame, share: float = SHARE) -> Weights:
    """Exact document counts of all shingles that at least ``share`` of the documents (two at least) hold."""
    rows = docs.filter("text is not null").select("text")
    documents = rows.count()
    least = max(2, int(np.ceil(share * documents)))
    counts = rows.mapInArrow(_bucket_counts, "range int, salt int, counts binary")
    left = rows.rdd.getNumPartitions()
    while left:  # each level adds up some MERGED tables of a range, so what a group holds does not grow with the tasks
        left = -(-left // MERGED) if left > MERGED else 0
        counts = counts.withColumn("salt", F.col("salt") % max(1, left)).groupBy("range", "salt").applyInArrow(_added, "range int, salt int, counts binary")
    heavy = [r["bucket"] for r in counts.mapInArrow(_heavy(least), "bucket long").collect()]  # BUCKETS numbers at most
    shared = docs.sparkSession.sparkContext.broadcast(np.array(heavy, np.int64))
    known = rows.mapInArrow(_candidates(shared), "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).filter(F.col("n") >= least).collect() if heavy else []
    return Weights(np.array([r["h"] for r in known], np.int64).view(np.uint64), np.array([r["n"] for r in known], np.float64), documents, least)


@lru_cache(maxsize=1)
def _variates(seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    shape = (ENTRIES, SLOTS)
    return rng.gamma(2.0, 1.0, shape).astype(np.float32), rng.gamma(2.0, 1.0, shape).astype(np.float32), rng.random(shape, np.float32)


def _samples(log_w: np.ndarray, r: np.ndarray, c: np.ndarray, beta: np.ndarray) -> np.ndarray:
    """The sampler's value per element, as ordered bits: ln w quantised on the grid of r and beta, then c / (y e^r)."""
    t = np.floor(log_w / r + beta)
    a = c * np.exp(-(r * (t - beta)) - r)
    return a.astype(np.float32).view(np.uint32).astype(np.uint64) << np.uint64(32)


@lru_cache(maxsize=2)
def _usual(seed: int, log_w: float) -> np.ndarray:
    r, c, beta = _variates(seed)
    return np.stack([_samples(np.float32(log_w), r[k], c[k], beta[k]) for k in range(ENTRIES)])


def signatures(h: np.ndarray, w: np.ndarray, start: np.ndarray, usual: float, seed: int = 13) -> np.ndarray:
    """Texts x ENTRIES consistent samples of shingles sorted by text; ``usual``: the weight that most shingles have."""
    slot, rest = (h & np.uint64(SLOTS - 1)).astype(np.int64), h >> np.uint64(16)
    table, (r, c, beta) = _usual(seed, float(np.float32(np.log(usual)))), _variates(seed)
    other = np.flatnonzero(w != usual)
    log_w, other_slot = np.log(w[other]).astype(np.float32), slot[other]
    out = np.empty((len(start), ENTRIES), np.uint64)
    for k in range(ENTRIES):
        v = table[k][slot]
        if len(other):
            v[other] = _samples(log_w, r[k][other_slot], c[k][other_slot], beta[k][other_slot])
        v |= rest
        out[:, k] = np.minimum.reduceat(v, start)
    return out


def _signer(shared):
    def run(batches):
        known: Weights = shared.value
        for batch in sliced(batches, 4096, TRIM):
            null = batch.column("text").is_null().to_pylist()
            same: list = []
            keys: list = [None] * batch.num_rows
            for a, b, data, offsets in _chunks(batch):
                same += [None if null[a + i] else hashlib.blake2b(data[offsets[i] : offsets[i + 1]], digest_size=16).digest() for i in range(b - a)]
                text, h, tf = shingled(data, offsets)
                if not len(h):
                    continue
                who, start = np.unique(text, return_index=True)
                got = signatures(h, tf * known.of(h), start, known.most)
                band = np.zeros((len(who), BANDS), np.uint64)
                with np.errstate(over="ignore"):
                    for j in range(ROWS):
                        band = mix(band * np.uint64(0x9DDFEA08EB382D69) + got[:, j::ROWS], j)
                    band = mix(band + np.arange(BANDS, dtype=np.uint64), 7).view(np.int64)
                for i, row in zip((a + who).tolist(), band.tolist()):
                    keys[i] = row
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(same, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], names=["doc_id", "same", "keys"])

    return run


def weighted_jaccard(one: tuple[np.ndarray, np.ndarray], two: tuple[np.ndarray, np.ndarray]) -> float:
    """Of two (sorted hashes, weights)."""
    (h, w), (g, v) = one, two
    if not len(h) or not len(g):
        return 0.0
    at = np.minimum(np.searchsorted(g, h), len(g) - 1)
    hit = g[at] == h
    both = np.minimum(w[hit], v[at[hit]]).sum()
    return float(both / (w.sum() + v.sum() - both))


def _verifier(shared, least: float):
    def run(batches):
        known: Weights = shared.value
        cache: dict = {}
        held = 0

        for batch in sliced(batches, least=TRIM):
            a, b, ta, tb = (batch.column(n).to_pylist() for n in ("a", "b", "ta", "tb"))
            keep: list[int] = []
            for lo, hi in slices([len(x) + len(y) for x, y in zip(ta, tb)], PIECE):
                if held > CACHED:
                    cache.clear()
                    held = 0
                new = {i: t for i, t in zip(a[lo:hi] + b[lo:hi], ta[lo:hi] + tb[lo:hi]) if i not in cache}
                text, h, tf = shingled(*encoded(list(new.values())))
                w, at = tf * known.of(h), np.searchsorted(text, np.arange(len(new) + 1))
                cache.update((i, (h[p:q], w[p:q])) for i, p, q in zip(new, at, at[1:]))
                held += len(h)
                keep += [k for k in range(lo, hi) if weighted_jaccard(cache[a[k]], cache[b[k]]) >= least - 1e-9]
            yield batch.select(["ca", "cb"]).take(pa.array(keep, pa.int64())).rename_columns(["a", "b"])

    return run


def similarities(texts: list[str], known: Weights, one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Weighted Jaccard of each text of ``one`` with each of ``two`` (indexes into texts), by matrix products.

    A shingle that occurs n times is n features, so the sum of minima is a dot product of 0/1 features times their weight.
    """
    text, h, tf = shingled(*encoded(texts))
    idf = known.of(h)
    total = np.bincount(text, weights=tf * idf, minlength=len(texts))
    row = np.repeat(np.arange(len(h)), tf)
    level = np.arange(len(row)) - np.repeat(np.cumsum(tf) - tf, tf)
    key, feature = np.unique(mix(h[row] + level.astype(np.uint64) * np.uint64(1 << 48)), return_inverse=True)
    order = np.argsort(feature, kind="stable")
    feature, text, root = feature[order], text[row][order], np.sqrt(idf[row][order])
    both = np.zeros((len(one), len(two)))
    for lo in range(0, len(key), 4096):
        a, b = np.searchsorted(feature, (lo, lo + 4096))
        dense = np.zeros((len(texts), min(4096, len(key) - lo)))
        dense[text[a:b], feature[a:b] - lo] = root[a:b]
        both += dense[one] @ dense[two].T
    return both / np.maximum(total[one][:, None] + total[two][None] - both, 1e-12)


def _block_linker(shared, least: float):
    def run(table: pa.Table) -> pa.Table:
        role, rep, comp = (table.column(n).to_numpy() for n in ("role", "rep", "comp"))
        one, two = np.flatnonzero(role == 1), np.flatnonzero(role == 0)
        links: list[tuple[int, int]] = []
        if len(one) and len(two):
            near = similarities(table.column("text").to_pylist(), shared.value, one, two) >= least - 1e-9
            near &= comp[one][:, None] != comp[two][None]
            parent: dict[int, int] = {}

            def root(v):
                while parent.setdefault(v, v) != v:
                    parent[v] = v = parent[parent[v]]
                return v

            for i, j in zip(*(x.tolist() for x in np.nonzero(near))):
                x, y = root(int(comp[one[i]])), root(int(comp[two[j]]))
                if x != y:
                    parent[max(x, y)] = min(x, y)
                    links.append((int(rep[one[i]]), int(rep[two[j]])))
        return pa.table({"a": pa.array([a for a, _ in links], pa.int64()), "b": pa.array([b for _, b in links], pa.int64())})

    return run


def classes(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, class_id (smallest id of its class), kept: one row per document."""
    text_batches(docs.sparkSession)
    keep = Scratch(docs.sparkSession)
    rows = docs.select("doc_id", "text")
    shared = docs.sparkSession.sparkContext.broadcast(weights(rows))
    signed = keep(rows.mapInArrow(_signer(shared), "doc_id long, same binary, keys array<long>"), "signatures")
    reps = keep(signed.filter("same is not null and doc_id is not null").groupBy("same").agg(F.min("doc_id").alias("rep"), F.min("keys").alias("keys")), "distinct-texts")
    band = reps.filter("keys is not null").select("rep", F.explode("keys").alias("key"))
    crowd = keep(band.groupBy("key").agg(F.min("rep").alias("lead"), F.count("*").alias("n")).filter("n > 1"), "buckets")
    band = keep(band.join(crowd.hint("merge"), "key").select("key", "rep", "lead"), "bucket-members")
    ids = band.select(F.col("rep").alias("doc_id")).distinct()
    texts = keep(rows.join(ids.hint("merge"), "doc_id").groupBy(F.col("doc_id").alias("id")).agg(F.min("text").alias("text")), "candidate-texts")

    def verified(pairs: DataFrame) -> DataFrame:
        """The classes ca and cb, as a and b, of those pairs of texts a and b that are similar."""
        right = texts.select(F.col("id").alias("b"), F.col("text").alias("tb"))
        left = texts.select(F.col("id").alias("a"), F.col("text").alias("ta"))
        full = pairs.hint("merge").join(right.hint("merge"), "b").hint("merge").join(left.hint("merge"), "a")
        with arrow_rows(docs.sparkSession, PAIR_ROWS):
            return keep(full.select("a", "b", "ca", "cb", "ta", "tb").mapInArrow(_verifier(shared, similarity), "a long, b long"), "verified")

    def blocks(large: DataFrame) -> DataFrame:
        """Links of crowded buckets, block against block, so that a text is sent once per block and not once per pair."""
        salt = lambda n, k: F.pmod(F.xxhash64(F.lit(k), "rep"), F.col(n)).cast("int")
        each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
        n = large.groupBy("key").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("ms"), F.ceil(F.sum((F.col("comp") != F.col("main")).cast("int")) / BLOCK).cast("int").alias("ss"))
        rows = large.join(keep(n, "crowds").hint("merge"), "key")
        inside = rows.withColumn("i", salt("ms", 1)).withColumn("j", each("ss")).withColumn("role", F.lit(0))
        asking = rows.filter("comp <> main").withColumn("j", salt("ss", 2)).withColumn("i", each("ms")).withColumn("role", F.lit(1))
        columns = ["key", "i", "j", "role", "rep", "comp"]
        full = inside.select(columns).unionByName(asking.select(columns)).join(texts.withColumnRenamed("id", "rep").hint("merge"), "rep")
        return keep(full.groupBy("key", "i", "j").applyInArrow(_block_linker(shared, similarity), "a long, b long"), "block-links")

    def joined(tree: DataFrame, links: DataFrame) -> DataFrame:
        """The classes of ``tree`` after more links between them."""
        edges = links.unionByName(tree.select(F.col("node").alias("a"), F.col("component").alias("b")))
        return keep(components(edges, keep, FEW_LINKS), "classes") if links.count() else tree

    def grouped(tree: DataFrame) -> tuple[DataFrame, int, int]:
        """key, rep, comp, main (the largest class) of buckets that still hold several classes, and bounds on the pairs of all and of one."""
        own = band.select("key", "rep").join(tree.withColumnRenamed("node", "rep").hint("merge"), "rep", "left").select("key", "rep", F.coalesce("component", "rep").alias("comp"))
        own = keep(own, "bucket-classes")
        each = own.groupBy("key", "comp").agg(F.count("*").alias("n"))
        many = each.groupBy("key").agg(F.max_by("comp", F.struct("n", -F.col("comp"))).alias("main"), F.count("*").alias("comps"), F.sum("n").alias("n"), F.max("n").alias("most"))
        many = keep(many.filter("comps > 1").select("key", "main", ((F.col("n") - F.col("most")) * F.col("n")).alias("pairs")), "open-buckets")
        pairs, most = (n or 0 for n in many.agg(F.sum("pairs"), F.max("pairs")).first())
        return keep(own.join(many.hint("merge"), "key"), "open-members"), pairs, most

    first = verified(band.filter("rep <> lead").select(F.col("lead").alias("a"), F.col("rep").alias("b")).distinct().withColumns({"ca": F.col("a"), "cb": F.col("b")}))
    tree = keep(components(first, keep, FEW_LINKS), "classes")
    (left, pairs, most), few, before = grouped(tree), PAIRS_PER_TEXT * reps.count(), None
    for k in range(ROUNDS):
        if pairs <= few or before and pairs > 0.8 * before:
            break
        before = pairs
        pick = keep(left.filter("comp = main").groupBy("key").agg(F.min_by("rep", F.xxhash64(F.lit(k), "rep")).alias("lead")), "leaders")
        more = left.filter("comp <> main").join(pick.hint("merge"), "key").select(F.least("rep", "lead").alias("a"), F.greatest("rep", "lead").alias("b"), F.least("comp", "main").alias("ca"), F.greatest("comp", "main").alias("cb"))
        tree = joined(tree, verified(more.distinct()))
        left, pairs, most = grouped(tree)
    # What leaders did not join: members outside a bucket's largest class against all its members of other classes.
    small, large = left.filter(F.col("pairs") <= BLOCK_PAIRS), left.filter(F.col("pairs") > BLOCK_PAIRS)
    strange = small.filter("comp <> main").select("key", F.col("rep").alias("x"), F.col("comp").alias("cx"))
    rest = strange.join(small.select("key", "rep", "comp"), "key").filter("comp <> cx").select(F.least("rep", "x").alias("a"), F.greatest("rep", "x").alias("b"), F.least("comp", "cx").alias("ca"), F.greatest("comp", "cx").alias("cb"))
    if pairs:
        links = verified(rest.distinct())
        tree = joined(tree, links.unionByName(blocks(large)) if most > BLOCK_PAIRS else links)
    named = keep(reps.join(tree.withColumnRenamed("node", "rep").hint("merge"), "rep", "left").select("same", F.coalesce("component", "rep").alias("class_id")), "class-of-text")
    out = signed.select("doc_id", "same").join(named.hint("merge"), "same", "left").select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"))
    return keep.result(out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("class_id"), F.lit(True))), "document-classes")


def dedup(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """``docs`` less all but one document of each class."""
    gone = stored(classes(docs, similarity).filter("not kept").select(F.col("doc_id").alias("__chartrel_gone")).distinct(), "near-copies")
    return docs.join(gone.hint("merge"), F.col("doc_id") == F.col("__chartrel_gone"), "left_anti")
