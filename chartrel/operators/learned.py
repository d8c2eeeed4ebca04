"""The relation classifier on Spark: training on the driver or data-parallel, inference in Arrow batches, models as tables."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import cluster
from .nn import CLASSES, SIDE, Adam, Cnn, fit, shrink

PREDICTED = "chart_id long, series_no int, r int, g int, b int, k int, relation string, score double, flat string"


def examples(images: DataFrame, truth: DataFrame, rule: str = "corrected") -> DataFrame:
    """chart_id, series_key, x (SIDE * SIDE floats), y: single-series images of labelled charts, found by colour.

    truth: chart_id, series_key, r, g, b, relation. The masks come from the same chain that prediction uses.
    """
    labels = truth.filter(F.col("relation").isin(*CLASSES)).groupBy("chart_id").agg(F.collect_list(F.struct("series_key", "r", "g", "b", "relation")).alias("s"))

    def run(batches):
        for batch in batches:
            rows = []
            for c, w, h, data, s in zip(*(batch.column(n).to_pylist() for n in ("chart_id", "width", "height", "data", "s"))):
                _, found = cluster.np_series(np.frombuffer(data, np.uint8).reshape(h, w, 3), rule)
                if not found:
                    continue
                hues = cluster.np_hsv(np.array([f[0] for f in found]))[:, 0]
                for e in s:
                    hue = int(cluster.np_hsv(np.array([[e["r"], e["g"], e["b"]]]))[0, 0])
                    gap = np.minimum(np.abs(hues - hue), 180 - np.abs(hues - hue))
                    if gap.min() <= cluster.WIDTHS[0]:
                        rows.append({"chart_id": c, "series_key": e["series_key"], "x": shrink(found[int(gap.argmin())][1]).ravel().tolist(), "y": CLASSES.index(e["relation"])})
            if rows:
                yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("chart_id", pa.int64()), ("series_key", pa.string()), ("x", pa.list_(pa.float32())), ("y", pa.int32())]))

    return images.select("chart_id", "width", "height", "data").join(labels, "chart_id").mapInArrow(run, "chart_id long, series_key string, x array<float>, y int")


def train(rows: DataFrame, model: Cnn | None = None, epochs: int = 30, seed: int = 0, most: int = 4000, validate: bool = False) -> Cnn:
    """A model from examples (chart_id, x, and y or an array of classes, one per head); at most ``most`` of them (by id) are brought to the driver.

    ``validate`` trains on the charts of one half of a draw and keeps the epoch that does best on the other half.
    """
    got = rows.orderBy("chart_id", *(c for c in ("series_key",) if c in rows.columns)).limit(most).collect()
    if not got:
        return model or Cnn(1, seed)
    x = np.array([r["x"] for r in got], np.float32).reshape(-1, SIDE, SIDE)
    y = np.array([r["y"] if isinstance(r["y"], list) else [r["y"]] for r in got])
    held = np.array([zlib.crc32(f"{seed}:{r['chart_id']}".encode()) % 2 == 1 for r in got]) if validate else np.zeros(len(got), bool)
    if held.all() or not held.any():
        return fit(x, y, model, epochs, seed=seed)
    return fit(x[~held], y[~held], model, epochs, seed=seed, check=(x[held], y[held]))


def train_parallel(rows: DataFrame, epochs: int = 5, seed: int = 0, rate: float = 5e-3) -> Cnn:
    """Synchronous data-parallel training: each round sums gradients on the executors by weight, one step on the driver."""
    spark, model, adam = rows.sparkSession, Cnn(1, seed), Adam(rate)

    for _ in range(epochs):
        shared = spark.sparkContext.broadcast(model.w)

        def run(batches, shared=shared):
            net, total, n = Cnn(1, weights=shared.value), {}, 0
            for batch in batches:
                x = np.array(batch.column("x").to_pylist(), np.float32).reshape(-1, SIDE, SIDE)
                if len(x):
                    g, _ = net.gradient(x, np.array(batch.column("y").to_pylist())[:, None])
                    n += len(x)
                    total = {k: total.get(k, 0) + v for k, v in g.items()}
            if n:
                yield pa.RecordBatch.from_pylist([{"name": k, "value": v.ravel().astype(float).tolist(), "n": n} for k, v in total.items()], schema=pa.schema([("name", pa.string()), ("value", pa.list_(pa.float64())), ("n", pa.int64())]))

        parts = rows.select("x", "y").mapInArrow(run, "name string, value array<double>, n long")
        sums = parts.select("name", "n", F.posexplode("value").alias("i", "v")).groupBy("name", "i").agg(F.sum("v").alias("v"), F.sum("n").alias("n"))
        got: dict[str, list] = {}
        for r in sums.groupBy("name").agg(F.sort_array(F.collect_list(F.struct("i", "v", "n"))).alias("a")).collect():  # one row per layer
            got[r["name"]] = [(e["v"], e["n"]) for e in r["a"]]
        adam.step(model.w, {k: (np.array([v for v, _ in a]) / a[0][1]).reshape(model.w[k].shape).astype(np.float32) for k, a in got.items()})
    return model


def save_model(spark: SparkSession, model: Cnn, path: str) -> None:
    """Layers as rows: name, shape, values."""
    rows = [(k, list(v.shape), [float(x) for x in v.ravel()]) for k, v in model.w.items()]
    spark.createDataFrame(rows, "name string, shape array<int>, values array<float>").write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> Cnn:
    w = {r["name"]: np.array(r["values"], np.float32).reshape(r["shape"]) for r in spark.read.parquet(path).collect()}  # one row per layer
    return Cnn(w["o"].shape[1] // 3, weights=w)


def mask_relation(mask: np.ndarray, cut: tuple[int, int] = (2, 5)) -> str:
    """Programmed classifier: rank correlation of columns and mean heights of the ink."""
    ys, xs = np.nonzero(mask)
    if not len(xs):
        return "neutral"
    n = np.bincount(xs)
    cols = np.flatnonzero(n)
    y = -(np.bincount(xs, weights=ys)[cols] * 1000 // n[cols])
    if len(cols) < 2 or (y == y[0]).all():
        return "neutral"
    _, where, many = np.unique(y, return_inverse=True, return_counts=True)
    b = (2 * (np.cumsum(many) - many) + many + 1)[where].astype(object)
    a = 2 * np.arange(1, len(cols) + 1).astype(object)
    m = len(cols)
    num = m * (a * b).sum() - a.sum() * b.sum()
    den = (m * (a * a).sum() - a.sum() ** 2) * (m * (b * b).sum() - b.sum() ** 2)
    if cut[1] ** 2 * num * num <= cut[0] ** 2 * den:
        return "neutral"
    return "increasing" if num > 0 else "decreasing"


def predict(images: DataFrame, model: Cnn | None = None, rule: str = "corrected", clean: bool = True, threshold: int = cluster.SATURATION, widths: tuple[int, int, int] = cluster.WIDTHS) -> DataFrame:
    """One row per found series of every image: cleaning, choice of k, clustering, masks and relation in one pass over the pixels.

    Without a model the programmed classifier alone decides; ``flat`` always holds its answer.
    """
    return predict_each(images, {"": {"model": model, "rule": rule, "clean": clean, "threshold": threshold, "widths": widths}}).drop("variant")


def predict_each(images: DataFrame, variants: dict[str, dict]) -> DataFrame:
    """``variant``, and what ``predict`` returns for its settings: all variants in one pass over the images.

    Variants that differ in their model only share the chain up to the masks.
    """
    chains: dict[tuple, list[tuple[str, Cnn | None]]] = {}
    for name, how in variants.items():
        chain = how.get("rule", "corrected"), how.get("threshold", cluster.SATURATION), how.get("clean", True), how.get("widths", cluster.WIDTHS)
        chains.setdefault(chain, []).append((name, how.get("model")))
    shared = images.sparkSession.sparkContext.broadcast(chains)

    def run(batches):
        for batch in batches:
            out = []
            pixels = [(c, np.frombuffer(data, np.uint8).reshape(h, w, 3)) for c, w, h, data in zip(*(batch.column(n).to_pylist() for n in ("chart_id", "width", "height", "data")))]
            for chain, nets in shared.value.items():
                rows, xs = [], []
                for c, img in pixels:
                    k, found = cluster.np_series(img, *chain)
                    for no, (rgb, mask) in enumerate(found, 1):
                        plain = mask_relation(mask)
                        rows.append({"chart_id": c, "series_no": no, "r": rgb[0], "g": rgb[1], "b": rgb[2], "k": k, "relation": plain, "score": 1.0, "flat": plain})
                        xs.append(shrink(mask))
                for name, net in nets:
                    p = net.forward(np.stack(xs))[0][:, 0] if net is not None and rows else None
                    out += [r | {"variant": name} if p is None else r | {"variant": name, "relation": CLASSES[int(p[i].argmax())], "score": float(p[i].max())} for i, r in enumerate(rows)]
            if out:
                yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("variant", pa.string()), ("chart_id", pa.int64()), ("series_no", pa.int32()), *((n, pa.int32()) for n in "rgb"), ("k", pa.int32()), ("relation", pa.string()), ("score", pa.float64()), ("flat", pa.string())]))

    return images.select("chart_id", "width", "height", "data").mapInArrow(run, f"variant string, {PREDICTED}")


def _whole(w: int, h: int, data: bytes) -> np.ndarray:
    """All ink of a chart, whatever its colour."""
    img = np.frombuffer(data, np.uint8).reshape(h, w, 3)
    return shrink((img != img[0, 0]).any(axis=2))


def count_examples(images: DataFrame, truth: DataFrame) -> DataFrame:
    """chart_id, x, y: whole charts and, per relation, how many of their series have it (two stands for more)."""
    n = truth.groupBy("chart_id").agg(F.array(*(F.least(F.lit(2), F.sum((F.col("relation") == r).cast("int"))).cast("int") for r in CLASSES)).alias("y"))

    def run(batches):
        for batch in batches:
            ids, ys = batch.column("chart_id").to_pylist(), batch.column("y").to_pylist()
            if ids:
                xs = [_whole(*r).ravel().tolist() for r in zip(*(batch.column(c).to_pylist() for c in ("width", "height", "data")))]
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(xs, pa.list_(pa.float32())), pa.array(ys, pa.list_(pa.int32()))], names=["chart_id", "x", "y"])

    return images.select("chart_id", "width", "height", "data").join(n, "chart_id").mapInArrow(run, "chart_id long, x array<float>, y array<int>")


def count_head(images: DataFrame, model: Cnn) -> DataFrame:
    """Learning alone: a network with one head per relation reads its count off the whole chart's ink; as many rows of each relation."""
    shared = images.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            ids = batch.column("chart_id").to_pylist()
            if not ids:
                continue
            p, _ = shared.value.forward(np.stack([_whole(*r) for r in zip(*(batch.column(c).to_pylist() for c in ("width", "height", "data")))]))
            rows = [(c, r) for c, k in zip(ids, p.argmax(axis=2).tolist()) for r, n in zip(CLASSES, k) for _ in range(n)]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array([c for c, _ in rows], pa.int64()), pa.array(range(1, len(rows) + 1), pa.int32()), pa.array([r for _, r in rows], pa.string())], names=["chart_id", "series_no", "relation"])

    return images.select("chart_id", "width", "height", "data").mapInArrow(run, "chart_id long, series_no int, relation string")
