"""Embedding near-dedup by an inverted multi-index.

Each half of the unit vectors has a codebook of its own, fitted on a bounded sample; the pair of nearest centres is a
vector's cell in the product grid. A vector visits cells in order of summed distance (a multi-sequence traversal) as
many as the calibration asks for: the number after which a pair at exactly the wanted cosine, in random directions from
sampled vectors, is met from one side or the other with the target recall. All rows are indexed and all rows search.

What travels to the visited cells is an id and a code of 128 bits, the signs of random projections; pairs whose codes differ
in more bits than all but a few in 100,000 pairs at the wanted cosine do are not looked at further. Only vectors that
meet such a partner in a cell travel there whole, and those are verified by their cosine in double precision, block by
block, so nothing below it is linked and a crowd of near copies needs no list of its pairs.

Defined results: vectors that are null, zero, or hold null or non-finite components link with nothing; vectors of
different lengths have no cosine, so each length has an index of its own, one after the other. Components keep the
precision of their type. Equal vectors are compared once and count as often as they occur, so a crowd of copies costs one row.
Repeated ids are separate vectors; a null id takes no part. An empty table gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, parts
from .components import components

COSINE, RECALL = 0.9, 0.995
#: Vectors of the fitting sample, vectors of a cell aimed at, rows of a block that is compared at once.
SAMPLE, CELL, BLOCK = 20_000, 256, 2048
#: Centres of a codebook at least, if there are as many vectors: a small table has a grid that prunes, too.
CENTRES = 16
PROBES = 1500
#: Bits of a code, and the share of pairs at the wanted cosine that codes may lose.
CODE, LOST = 128, 5e-5


def squared(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(axis=1)[:, None] - 2 * x @ c.T + (c * c).sum(axis=1), 0)


def codebook(x: np.ndarray, k: int, rng, rounds: int = 12) -> np.ndarray:
    centre = x[rng.choice(len(x), min(k, len(x)), replace=False)]
    for _ in range(rounds):
        near = squared(x, centre).argmin(axis=1)
        total = np.zeros_like(centre)
        np.add.at(total, near, x)
        n = np.bincount(near, minlength=len(centre))
        centre = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], centre)
    return centre


def multi_sequence(d1: np.ndarray, d2: np.ndarray, visits: int) -> list[int]:
    """The ``visits`` cells of least d1[i] + d2[j], nearest first, by a heap over the two sorted lists."""
    o1, o2, k2 = np.argsort(d1, kind="stable"), np.argsort(d2, kind="stable"), len(d2)
    heap, seen, out = [(float(d1[o1[0]] + d2[o2[0]]), 0, 0)], {(0, 0)}, []
    while heap and len(out) < visits:
        _, i, j = heapq.heappop(heap)
        out.append(int(o1[i]) * k2 + int(o2[j]))
        for a, b in ((i + 1, j), (i, j + 1)):
            if a < len(o1) and b < len(o2) and (a, b) not in seen:
                seen.add((a, b))
                heapq.heappush(heap, (float(d1[o1[a]] + d2[o2[b]]), a, b))
    return out


class MultiIndex:
    """Two codebooks and the number of cells that a search visits."""

    def __init__(self, sample: np.ndarray, total: int, cosine: float = COSINE, recall: float = RECALL, cell: int = CELL, seed: int = 9):
        rng = np.random.default_rng(seed)
        self.half = sample.shape[1] // 2
        k = int(max(1, min(max(CENTRES, np.sqrt(total / cell)), len(sample) / 4)))
        self.planes = rng.normal(size=(sample.shape[1], CODE))
        self.apart = code_radius(cosine)
        self.c1, self.c2 = codebook(sample[:, : self.half], k, rng), codebook(sample[:, self.half :], k, rng)
        self.visits = self._calibrated(sample, cosine, recall, rng)

    def distances(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return squared(unit[:, : self.half], self.c1), squared(unit[:, self.half :], self.c2)

    def cells(self, unit: np.ndarray) -> np.ndarray:
        d1, d2 = self.distances(unit)
        return d1.argmin(axis=1) * len(self.c2) + d2.argmin(axis=1)

    def _calibrated(self, sample, cosine, recall, rng) -> int:
        x = sample[rng.choice(len(sample), min(PROBES, len(sample)), replace=False)]
        z = rng.normal(size=x.shape)
        z -= (z * x).sum(axis=1)[:, None] * x
        y = cosine * x + np.sqrt(max(0.0, 1 - cosine**2)) * z / np.maximum(np.linalg.norm(z, axis=1), 1e-300)[:, None]
        rank = np.full(len(x), np.iinfo(np.int64).max)
        for p, q in ((x, y), (y, x)):
            (p1, p2), (q1, q2) = self.distances(p), self.distances(q)
            i, j, own = q1.argmin(axis=1), q2.argmin(axis=1), np.arange(len(x))
            at = p1[own, i] + p2[own, j]
            # Cells nearer than the other's: for each first centre, how many second centres stay below.
            low = np.sort(p2, axis=1)
            nearer = np.array([np.searchsorted(low[r], at[r] - p1[r], side="left").sum() for r in range(len(x))])
            rank = np.minimum(rank, nearer)
        return int(min(len(self.c1) * len(self.c2), np.quantile(rank, recall) + 1))

    def codes(self, unit: np.ndarray) -> np.ndarray:
        """CODE bits per vector: on which side of each random plane it lies."""
        return np.packbits(unit @ self.planes > 0, axis=1)

    def search_order(self, unit: np.ndarray) -> list[list[int]]:
        d1, d2 = self.distances(unit)
        return [multi_sequence(d1[r], d2[r], self.visits) for r in range(len(unit))]


def code_radius(cosine: float, lost: float = LOST) -> int:
    """Bits in which the codes of all but the share ``lost`` of pairs at that cosine differ at most: a binomial quantile."""
    p = float(np.arccos(np.clip(cosine, -1, 1)) / np.pi)
    if p <= 0:
        return 0
    k = np.arange(1, CODE + 1)
    log = np.concatenate(([0.0], np.cumsum(np.log((CODE - k + 1) / k)))) + np.arange(CODE + 1) * np.log(p) + (CODE - np.arange(CODE + 1)) * np.log1p(-p)
    return int(np.searchsorted(np.cumsum(np.exp(log)), 1 - lost))


def units(raw: np.ndarray) -> np.ndarray:
    """Rows at length one, in doubles; scaled first, so that no finite component overflows."""
    x = raw.astype(np.float64)
    x /= np.abs(x).max(axis=1, keepdims=True, initial=1e-320)
    return x / np.sqrt((x * x).sum(axis=1))[:, None]


def _whole(raw: list[bytes], kind: str) -> np.ndarray:
    return units(np.frombuffer(b"".join(raw), kind).reshape(len(raw), -1))


def _keyed(kind: str):
    def run(batches):
        for batch in batches:
            blobs = [np.asarray(v, kind).tobytes() for v in batch.column("embedding").to_pylist()]
            d = [hashlib.blake2b(b, digest_size=16).digest() for b in blobs]
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(d, pa.binary()), pa.array(blobs, pa.binary())], names=["vec_id", "same", "raw"])

    return run


def _indexer(shared, kind: str):
    def run(batches):
        index: MultiIndex = shared.value
        for batch in batches:
            for lo in range(0, batch.num_rows, BLOCK):
                part = batch.slice(lo, BLOCK)
                unit = _whole(part.column("raw").to_pylist(), kind)
                code = [c.tobytes() for c in index.codes(unit)]
                yield pa.RecordBatch.from_arrays([part.column("rep"), pa.array(code, pa.binary()), pa.array(index.cells(unit).astype(np.int32)), pa.array(index.search_order(unit), pa.list_(pa.int32()))], names=["rep", "code", "home", "visits"])

    return run


_MET = pa.schema([("cell", pa.int32()), ("rep", pa.int64()), ("role", pa.int32())])
_FOUND = pa.schema([("rep", pa.int64()), ("links", pa.int64()), ("a", pa.int64()), ("b", pa.int64())])


def _sifter(apart: int):
    def run(table: pa.Table) -> pa.Table:
        """Members (role 0) and visitors (role 1) of one block whose code lies near that of one of the other kind."""
        role, rep = table.column("role").to_numpy(), table.column("rep").to_numpy()
        member, visitor = np.flatnonzero(role == 0), np.flatnonzero(role == 1)
        if not len(member) or not len(visitor):
            return _MET.empty_table()
        code = np.frombuffer(b"".join(table.column("code").to_pylist()), np.uint64).reshape(len(rep), -1)
        hit = np.zeros(len(rep), bool)
        for lo in range(0, len(visitor), 512):
            part = visitor[lo : lo + 512]
            far = np.zeros((len(part), len(member)), np.uint8)
            for w in range(code.shape[1]):
                far += np.bitwise_count(code[part, w][:, None] ^ code[member, w][None])
            near = (far <= apart) & (rep[part][:, None] != rep[member][None])
            hit[part] |= near.any(axis=1)
            hit[member] |= near.any(axis=0)
        at = np.flatnonzero(hit)
        return pa.table([pa.array(np.full(len(at), table.column("cell")[0].as_py(), np.int32)), pa.array(rep[at]), pa.array(role[at].astype(np.int32))], schema=_MET)

    return run


def _comparer(cosine: float, kind: str):
    def run(table: pa.Table) -> pa.Table:
        """Counts for both sides of the pairs met in one block, and a spanning forest of its links."""
        role = table.column("role").to_numpy()
        rep, copies, home = table.column("rep").to_numpy(), table.column("copies").to_numpy(), table.column("home").to_numpy()
        member, visitor = np.flatnonzero(role == 0), np.flatnonzero(role == 1)
        if not len(member) or not len(visitor):
            return _FOUND.empty_table()
        unit = _whole(table.column("raw").to_pylist(), kind)
        lists = table.column("visits").to_pylist()
        home_at = {}
        for m in member.tolist():  # members that visit a home themselves meet its vectors there
            for c in lists[m]:
                home_at.setdefault(c, []).append(m)
        count, edges = np.zeros(len(rep), np.int64), []
        parent = np.arange(len(rep))

        def root(v: int) -> int:
            while parent[v] != v:
                parent[v] = v = parent[parent[v]]
            return v

        slot = np.full(len(rep), -1)
        slot[member] = np.arange(len(member))
        for lo in range(0, len(visitor), 512):
            part = visitor[lo : lo + 512]
            near = (unit[part] @ unit[member].T >= cosine) & (rep[part][:, None] != rep[member][None])
            count[part] += near @ copies[member]
            for c in np.unique(home[part]).tolist():
                rows = np.flatnonzero(home[part] == c)
                back = near[rows]
                if c in home_at:
                    back[:, slot[home_at[c]]] = False
                count[member] += back.T @ copies[part[rows]]
            for i in np.flatnonzero(near.any(axis=1)).tolist():
                own = np.flatnonzero(near[i])
                v = root(int(part[i]))
                loose = own[parent[member[own]] != v]
                for j in loose.tolist():
                    a, b = root(int(part[i])), root(int(member[j]))
                    if a != b:
                        parent[max(a, b)] = min(a, b)
                        edges.append((int(rep[part[i]]), int(rep[member[j]])))
        at = np.flatnonzero(count)
        return pa.table([pa.array([*rep[at].tolist(), *([None] * len(edges))], pa.int64()), pa.array([*count[at].tolist(), *([0] * len(edges))], pa.int64()), pa.array([*([None] * len(at)), *(a for a, _ in edges)], pa.int64()), pa.array([*([None] * len(at)), *(b for _, b in edges)], pa.int64())], schema=_FOUND)

    return run


def _dealt(inside: DataFrame, asking: DataFrame, keep: Scratch, name: str, least: int = 1) -> DataFrame:
    """Members and visitors of every cell, each cell in blocks of BLOCK members by 4 BLOCK visitors: columns m and v number them.

    A cell of more than BLOCK / 16 is cut into ``least`` runs of both, as far as they go round, so that one crowd is not one task.
    """
    salt = lambda n, k: F.pmod(F.xxhash64(F.lit(k), "rep"), F.col(n)).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    cut = lambda block: F.greatest(F.ceil(F.count("*") / block), F.least(F.lit(least), F.ceil(F.count("*") / (block // 16)))).cast("int")
    members = inside.groupBy("cell").agg(cut(BLOCK).alias("ms"))
    visitors = asking.groupBy("cell").agg(cut(4 * BLOCK).alias("vs"))
    crowd = keep(members.join(visitors, "cell"), f"{name}-cells")
    one = inside.join(crowd, "cell").withColumn("m", salt("ms", 1)).withColumn("v", each("vs")).drop("ms", "vs")
    two = asking.join(crowd, "cell").withColumn("v", salt("vs", 2)).withColumn("m", each("ms")).drop("ms", "vs")
    return one.unionByName(two)


def _linked(good: DataFrame, kind: str, cosine: float, recall: float, cell: int, keep: Scratch) -> DataFrame:
    """vec_id, n_links, component_id, kept for sound vectors of one length."""
    spark = good.sparkSession
    keyed = keep(good.select("vec_id", "embedding").mapInArrow(_keyed(kind), "vec_id long, same binary, raw binary"), "vectors")
    reps = keep(keyed.groupBy("same").agg(F.min("vec_id").alias("least"), F.count("*").alias("copies"), F.min("raw").alias("raw")).withColumn("rep", F.xxhash64("same")), "distinct-vectors")
    total = reps.count()
    share = min(1.0, SAMPLE / total)
    got = reps.filter(F.pmod(F.xxhash64(F.lit(4), "same"), F.lit(1 << 30)) < int(share * (1 << 30))).select("raw").limit(2 * SAMPLE).collect() if total > SAMPLE else reps.select("raw").collect()
    index = MultiIndex(_whole(sorted(bytes(r["raw"]) for r in got), kind), total, cosine, recall, cell)
    shared = spark.sparkContext.broadcast(index)  # two codebooks of sqrt(total / cell) centres, a quarter of the sample at most, and the planes
    # Ids may repeat among different vectors: the digest's own number names a representative.
    placed = keep(reps.select("rep", "raw").repartition(parts(spark)).mapInArrow(_indexer(shared, kind), "rep long, code binary, home int, visits array<int>"), "placed-vectors")
    dealt = _dealt(placed.select(F.col("home").alias("cell"), "rep", "code", F.lit(0).alias("role")), placed.select(F.explode("visits").alias("cell"), "rep", "code", F.lit(1).alias("role")), keep, "code")
    near = keep(dealt.groupBy("cell", "m", "v").applyInArrow(_sifter(index.apart), "cell int, rep long, role int").distinct(), "near-codes")
    whole = near.join(placed.select("rep", "home", "visits").hint("merge"), "rep").join(reps.select("rep", "copies", "raw").hint("merge"), "rep")
    whole = whole.withColumn("visits", F.when(F.col("role") == 0, F.col("visits")).otherwise(F.array().cast("array<int>")))
    whole = keep(whole, "near-vectors")
    met = keep(_dealt(whole.filter("role = 0"), whole.filter("role = 1"), keep, "vector", 4).groupBy("cell", "m", "v").applyInArrow(_comparer(cosine, kind), "rep long, links long, a long, b long"), "met-pairs")
    counts = met.filter("rep is not null").groupBy("rep").agg(F.sum("links").alias("links"))
    tree = components(met.filter("a is not null").select("a", "b"), keep)
    joined = reps.select("rep", "least", "copies", "same").join(tree.withColumnRenamed("node", "rep"), "rep", "left").join(counts, "rep", "left")
    joined = keep(joined.select("same", "copies", "least", F.coalesce("component", "rep").alias("component"), F.coalesce("links", F.lit(0)).alias("links")), "vector-classes")
    name = keep(joined.groupBy("component").agg(F.min("least").alias("component_id")), "component-names")
    named = keep(joined.join(name.hint("merge"), "component").select("same", (F.col("links") + F.col("copies") - 1).cast("long").alias("n_links"), "component_id"), "named-classes")
    return keyed.select("vec_id", "same").join(named.hint("merge"), "same").select("vec_id", "n_links", "component_id", (F.col("vec_id") == F.col("component_id")).alias("kept"))


def near_duplicates(vectors: DataFrame, cosine: float = COSINE, recall: float = RECALL, cell: int = CELL) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of (vec_id, embedding)."""
    keep = Scratch(vectors.sparkSession)
    kind = "f4" if dict(vectors.dtypes)["embedding"] == "array<float>" else "f8"
    rows = vectors.select("vec_id", F.col("embedding").cast("array<float>" if kind == "f4" else "array<double>").alias("embedding"))
    sound = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & F.exists("embedding", lambda v: v != 0)
    rows = rows.withColumn("_d", F.when(sound, F.size("embedding")))
    found = rows.groupBy("_d").count().collect()  # one row per length that occurs
    many = sorted(r["_d"] for r in found if r["_d"] is not None and r["count"] > 1)
    out = rows.filter(~F.coalesce(F.col("_d").isin(many), F.lit(False))).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.col("vec_id").isNotNull().alias("kept"))
    for width in many:
        out = out.unionByName(_linked(rows.filter(F.col("_d") == width), kind, cosine, recall, cell, keep))
    return keep.result(out, "vector-groups")
