"""Facets and their text: layout and learned detection, glyph matching, rotation, confusions, and assignment.

The reader matches glyphs of the package's own 5 x 7 bitmap font; any engine with ``read(box) -> str`` can stand in for it.
"""

from __future__ import annotations

import string

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.draws import draw
from .raster import H, IH, IW, LEFT, TOP, W

GW, GH = 5, 7
ALPHABET = string.ascii_letters + string.digits + " "
FACET = "chart_id long, kind string, ordinal int, x0 int, y0 int, x1 int, y1 int, score double"


def glyphs(seed: int = 20) -> dict[str, np.ndarray]:
    """A bitmap per character, drawn from a seed: distinct by at least nine of 35 cells, ink in every column and row."""
    rng, out = np.random.default_rng(seed), {" ": np.zeros((GH, GW), np.uint8)}
    for c in ALPHABET[:-1]:
        while True:
            g = (rng.random((GH, GW)) < 0.5).astype(np.uint8)
            if g.any(axis=0).all() and g.any(axis=1).all() and all((g != o).sum() >= 9 for o in out.values()):
                out[c] = g
                break
    return out


FONT = glyphs()
_TEMPLATES = np.stack([FONT[c].ravel() for c in ALPHABET]).astype(np.int32)


def drawn(text: str) -> np.ndarray:
    """A text as 0/1 ink, one blank column between glyphs."""
    cells = [np.hstack((FONT.get(c, FONT[" "]), np.zeros((GH, 1), np.uint8))) for c in text]
    return np.hstack(cells)[:, :-1] if cells else np.zeros((GH, 0), np.uint8)


def read(ink: np.ndarray) -> tuple[str, float]:
    """Text of a crop of one line and the mean share of cells that agree."""
    if ink.shape[0] < GH or ink.shape[1] < GW:
        return "", 0.0
    out, score = [], []
    for x in range(0, ink.shape[1] - GW + 1, GW + 1):
        cell = ink[:GH, x : x + GW].ravel().astype(np.int32)
        agree = (_TEMPLATES == cell).sum(axis=1)
        out.append(ALPHABET[int(agree.argmax())])
        score.append(agree.max() / (GW * GH))
    return "".join(out).rstrip(), float(np.mean(score)) if score else 0.0


def read_any(ink: np.ndarray, rotate: str = "manual", vertical: bool = False) -> str:
    """Reads a crop; a vertical one is turned first (``manual``), tried four ways (``auto``), or read as it is (``none``)."""
    if rotate == "manual":
        return read(np.rot90(ink, -1) if vertical else ink)[0]
    if rotate == "auto":
        return max((read(np.rot90(ink, k)) for k in range(4)), key=lambda r: r[1])[0]
    return read(ink)[0]


def place(img: np.ndarray, ink: np.ndarray, x: int, y: int, colour=(0, 0, 0)) -> tuple[int, int, int, int]:
    """Draws ink at (x, y), cut at the edge; returns its box, end exclusive."""
    ink = ink[: max(0, img.shape[0] - y), : max(0, img.shape[1] - x)]
    img[y : y + ink.shape[0], x : x + ink.shape[1]][ink > 0] = colour
    return x, y, x + ink.shape[1], y + ink.shape[0]


PLACES = ("title_x", "x_label_x", "y_label_y", "legend_y")


def annotated(images: DataFrame, labels: DataFrame, series: DataFrame, keep=lambda df: df) -> tuple[DataFrame, DataFrame]:
    """Images with title, axis labels and legend drawn in, and the true boxes and texts of those facets; ``keep`` may store what both come from.

    labels: chart_id, title, x_label, y_label and, where their places vary, title_x, x_label_x, y_label_y, legend_y; series: chart_id, series_no, series_label, r, g, b.
    """
    legend = series.groupBy("chart_id").agg(F.sort_array(F.collect_list(F.struct("series_no", "series_label", "r", "g", "b"))).alias("legend"))
    rows = images.select("chart_id", "width", "height", "channels", "data").join(labels.select("chart_id", "title", "x_label", "y_label", *(c for c in PLACES if c in labels.columns)), "chart_id").join(legend, "chart_id")
    box = pa.struct([("kind", pa.string()), ("ordinal", pa.int32()), *((n, pa.int32()) for n in ("x0", "y0", "x1", "y1")), ("text", pa.string())])
    wide, high = W + 90, H + 24

    def run(batches):
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                old = np.frombuffer(r["data"], np.uint8).reshape(r["height"], r["width"], 3)
                img = np.full((high, wide, 3), old[0, 0], np.uint8)
                img[12 : 12 + r["height"], 12 : 12 + r["width"]] = old
                found = []
                add = lambda kind, no, text, ink, x, y: found.append(dict(zip(("kind", "ordinal", "x0", "y0", "x1", "y1", "text"), (kind, no, *place(img, ink, x, y), text))))  # noqa: B023, E731
                add("title", 0, r["title"], drawn(r["title"]), r.get("title_x", 40), 2)
                add("x_label", 0, r["x_label"], drawn(r["x_label"]), r.get("x_label_x", 50), high - 9)
                add("y_label", 0, r["y_label"], np.rot90(drawn(r["y_label"])), 2, r.get("y_label_y", 26))
                for k, s in enumerate(r["legend"]):
                    y = r.get("legend_y", 20) + 11 * k
                    img[y + 1 : y + 6, W + 4 : W + 10] = (s["r"], s["g"], s["b"])
                    add("legend_text", k, s["series_label"], drawn(s["series_label"]), W + 13, y)
                out.append({"chart_id": r["chart_id"], "width": wide, "height": high, "channels": 3, "data": img.tobytes(), "facets": found})
            if out:
                yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("chart_id", pa.int64()), ("width", pa.int32()), ("height", pa.int32()), ("channels", pa.int32()), ("data", pa.binary()), ("facets", pa.list_(box))]))

    made = keep(rows.mapInArrow(run, "chart_id long, width int, height int, channels int, data binary, facets array<struct<kind:string,ordinal:int,x0:int,y0:int,x1:int,y1:int,text:string>>"))
    return made.select("chart_id", "width", "height", "channels", "data"), made.select("chart_id", F.inline("facets"))


def plot_area(facets_in: DataFrame) -> DataFrame:
    """The plot box of annotated images, as a facet of every chart."""
    return facets_in.select("chart_id").distinct().select("chart_id", F.lit("plot").alias("kind"), F.lit(0).alias("ordinal"), F.lit(12 + LEFT).alias("x0"), F.lit(12 + TOP).alias("y0"), F.lit(12 + LEFT + IW).alias("x1"), F.lit(12 + TOP + IH).alias("y1"))


def _runs(on: np.ndarray, gap: int) -> list[tuple[int, int]]:
    """Runs of set positions, joined over gaps of up to ``gap``."""
    at = np.flatnonzero(on)
    if not len(at):
        return []
    cut = np.flatnonzero(np.diff(at) > gap + 1)
    return list(zip(at[np.concatenate(([0], cut + 1))].tolist(), (at[np.concatenate((cut, [len(at) - 1]))] + 1).tolist()))


def layout(img: np.ndarray) -> list[tuple[str, int, int, int, int, int, float]]:
    """Programmed detector: dark ink by where it lies. Title on top, x label at the bottom, y label at the left, legend texts right of colour keys."""
    lum, hi = img.astype(int).sum(axis=2), img.max(axis=2).astype(int) - img.min(axis=2)
    dark = (lum < 120) & (hi < 40)
    out, high, wide = [], img.shape[0], img.shape[1]

    def box(y0, y1, x0, x1):
        part = dark[y0:y1, x0:x1]
        if not part.any():
            return None
        ys, xs = np.nonzero(part)
        return x0 + int(xs.min()), y0 + int(ys.min()), x0 + int(xs.max()) + 1, y0 + int(ys.max()) + 1

    for kind, area in (("title", (0, 11, 12, wide)), ("x_label", (high - 11, high, 12, wide)), ("y_label", (12, high - 12, 0, 11))):
        if b := box(*area):
            out.append((kind, 0, *b, 1.0))
    side = dark[12 : high - 12, W + 8 :]
    for k, (a, b) in enumerate(_runs(side.any(axis=1), 1)):
        if c := box(12 + a, 12 + b, W + 12, wide):
            out.append(("legend_text", k, *c, 1.0))
    return out


class Detector:
    """Single-shot detector: default boxes on a grid, per cell a linear class and offset head over pooled ink features.

    Boxes of training charts are matched to default boxes by overlap; the heads are fitted by softmax and least squares.
    """

    KINDS = ("none", "title", "x_label", "y_label", "legend_text")
    STEP = 6
    SHAPES = ((40, 7), (60, 7), (7, 40), (24, 7))

    def __init__(self, shape: tuple[int, int]):
        h, w = shape
        cy, cx = np.mgrid[3 : h : self.STEP, 3 : w : self.STEP]
        c = np.stack((cx.ravel(), cy.ravel()), axis=1)
        self.shape = shape
        self.boxes = np.concatenate([np.stack((c[:, 0] - s[0] / 2, c[:, 1] - s[1] / 2, c[:, 0] + s[0] / 2, c[:, 1] + s[1] / 2), axis=1) for s in self.SHAPES])
        self.kind = np.repeat(np.arange(len(self.SHAPES)), len(c))
        self.cls = self.off = None

    def features(self, img: np.ndarray) -> np.ndarray:
        """Per default box: ink inside, beyond each end, place on the canvas, shape."""
        dark = ((img.astype(int).sum(axis=2) < 120) & (img.max(axis=2).astype(int) - img.min(axis=2) < 40)).astype(float)
        area = np.pad(dark.cumsum(axis=0).cumsum(axis=1), ((1, 0), (1, 0)))
        h, w = self.shape

        def total(b):
            x0, y0, x1, y1 = (np.clip(b[:, i], 0, (w, h, w, h)[i]).astype(int) for i in range(4))
            return (area[y1, x1] - area[y0, x1] - area[y1, x0] + area[y0, x0]) / np.maximum(1, (x1 - x0) * (y1 - y0))

        b = self.boxes
        bw, bh = b[:, 2] - b[:, 0], b[:, 3] - b[:, 1]
        cols = [total(b)]
        for dx, dy in ((1, 0), (-1, 0), (0, 1), (0, -1)):
            cols.append(total(b + np.stack((dx * bw, dy * bh, dx * bw, dy * bh), axis=1)))
        for part in (0.25, 0.5, 0.75):
            cols.append(total(np.stack((b[:, 0], b[:, 1] + bh * (part - 0.25), b[:, 2], b[:, 1] + bh * part), axis=1)))
            cols.append(total(np.stack((b[:, 0] + bw * (part - 0.25), b[:, 1], b[:, 0] + bw * part, b[:, 3]), axis=1)))
        cx, cy = (b[:, 0] + b[:, 2]) / 2 / w, (b[:, 1] + b[:, 3]) / 2 / h
        place_ = [np.exp(-(((cx - px) / 0.12) ** 2)) for px in (0.05, 0.3, 0.5, 0.7, 0.85)] + [np.exp(-(((cy - py) / 0.08) ** 2)) for py in (0.04, 0.2, 0.35, 0.6, 0.95)]
        one = np.eye(len(self.SHAPES))[self.kind].T
        base = np.stack([*cols, *place_, *one, np.ones(len(b))], axis=1)
        return np.hstack((base, base[:, :1] * base))

    @staticmethod
    def overlap(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Intersection over union of every pair."""
        x0, y0 = np.maximum(a[:, None, 0], b[None, :, 0]), np.maximum(a[:, None, 1], b[None, :, 1])
        x1, y1 = np.minimum(a[:, None, 2], b[None, :, 2]), np.minimum(a[:, None, 3], b[None, :, 3])
        both = np.maximum(0, x1 - x0) * np.maximum(0, y1 - y0)
        size = lambda c: (c[:, 2] - c[:, 0]) * (c[:, 3] - c[:, 1])
        return both / np.maximum(1e-9, size(a)[:, None] + size(b)[None] - both)

    def train(self, images: list[np.ndarray], truth: list[list[tuple[str, int, int, int, int]]], rounds: int = 150, seed: int = 0) -> Detector:
        rng, fx, fy, fo = np.random.default_rng(seed), [], [], []
        for img, boxes in zip(images, truth):
            x = self.features(img)
            t = np.array([b[1:] for b in boxes], float).reshape(-1, 4)
            iou = self.overlap(self.boxes, t) if len(t) else np.zeros((len(self.boxes), 1))
            best = iou.argmax(axis=1)
            y = np.where(iou.max(axis=1) > 0.4, [self.KINDS.index(boxes[i][0]) if boxes else 0 for i in best], 0)
            for k in range(len(t)):
                j = int(iou[:, k].argmax())
                y[j], best[j] = self.KINDS.index(boxes[k][0]), k
            sure = np.flatnonzero(y > 0)
            none = rng.choice(np.flatnonzero((y == 0) & (iou.max(axis=1) < 0.3)), 3 * max(4, len(sure)), replace=False)
            inked = np.flatnonzero((y == 0) & (iou.max(axis=1) < 0.3) & (x[:, 0] > 0.2))[: 3 * max(4, len(sure))]
            use = np.concatenate((sure, none, inked))
            fx.append(x[use])
            fy.append(y[use])
            fo.append((t[best[use]] if len(t) else self.boxes[use]) - self.boxes[use])
        x, y, o = np.vstack(fx), np.concatenate(fy), np.vstack(fo)
        self.cls, grad2, hot = np.zeros((x.shape[1], len(self.KINDS))), 1e-6, np.eye(len(self.KINDS))[y]
        for _ in range(rounds * 4):
            z = x @ self.cls
            p = np.exp(z - z.max(axis=1, keepdims=True))
            g = x.T @ (p / p.sum(axis=1, keepdims=True) - hot) / len(x) + 1e-4 * self.cls
            grad2 = grad2 + g * g
            self.cls -= 0.5 * g / np.sqrt(grad2)
        m = y > 0
        self.off = np.linalg.lstsq(x[m].T @ x[m] + 1e-2 * np.eye(x.shape[1]), x[m].T @ o[m], rcond=None)[0]
        return self

    def detect(self, img: np.ndarray, least: float = 0.5) -> list[tuple[str, int, int, int, int, int, float]]:
        """Boxes by class after non-maximum suppression, in reading order."""
        x = self.features(img)
        z = x @ self.cls
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        boxes, out = self.boxes + x @ self.off, []
        for k in range(1, len(self.KINDS)):
            at = [i for i in np.argsort(-p[:, k]).tolist() if p[i, k] >= least]
            kept: list[int] = []
            for i in at:
                if not kept or self.overlap(boxes[i : i + 1], boxes[kept]).max() < 0.3:
                    kept.append(i)
            if self.KINDS[k] != "legend_text":
                kept = kept[:1]
            for no, i in enumerate(sorted(kept, key=lambda i: boxes[i, 1])):
                out.append((self.KINDS[k], no, *(int(round(v)) for v in boxes[i]), float(p[i, k])))
        return out


def detect(images: DataFrame, method: str = "layout", model: Detector | None = None) -> DataFrame:
    """chart_id, kind, ordinal, box, score by the programmed (``layout``) or the trained (``ssd``) detector."""
    shared = images.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            rows = []
            for c, w, h, data in zip(*(batch.column(n).to_pylist() for n in ("chart_id", "width", "height", "data"))):
                img = np.frombuffer(data, np.uint8).reshape(h, w, 3)
                for f in layout(img) if method == "layout" else shared.value.detect(img):
                    rows.append(dict(zip(("chart_id", "kind", "ordinal", "x0", "y0", "x1", "y1", "score"), (c, *f))))
            if rows:
                yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("chart_id", pa.int64()), ("kind", pa.string()), ("ordinal", pa.int32()), *((n, pa.int32()) for n in ("x0", "y0", "x1", "y1")), ("score", pa.float64())]))

    return images.select("chart_id", "width", "height", "data").mapInArrow(run, FACET)


def extract(images: DataFrame, facets_: DataFrame, rotate: str = "manual") -> DataFrame:
    """chart_id, kind, ordinal, text, cx, cy: the text of every facet, cropped from the raw image."""
    boxes = facets_.groupBy("chart_id").agg(F.collect_list(F.struct("kind", "ordinal", "x0", "y0", "x1", "y1")).alias("f"))

    def run(batches):
        for batch in batches:
            rows = []
            for c, w, h, data, fs in zip(*(batch.column(n).to_pylist() for n in ("chart_id", "width", "height", "data", "f"))):
                img = np.frombuffer(data, np.uint8).reshape(h, w, 3)
                dark = ((img.astype(int).sum(axis=2) < 120) & (img.max(axis=2).astype(int) - img.min(axis=2) < 40)).astype(np.uint8)
                for f in fs:
                    y0, y1, x0, x1 = max(0, f["y0"]), f["y1"], max(0, f["x0"]), f["x1"]
                    crop = dark[y0:y1, x0:x1]
                    ys, xs = np.nonzero(crop)
                    if len(ys):  # glyphs have ink in every row and column, so the ink's own box starts the grid
                        crop = crop[ys.min() : ys.max() + 1, xs.min() : xs.max() + 1]
                    rows.append({"chart_id": c, "kind": f["kind"], "ordinal": f["ordinal"], "text": read_any(crop, rotate, f["kind"] == "y_label"), "cx": (f["x0"] + f["x1"]) / 2, "cy": (f["y0"] + f["y1"]) / 2})
            if rows:
                yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("chart_id", pa.int64()), ("kind", pa.string()), ("ordinal", pa.int32()), ("text", pa.string()), ("cx", pa.float64()), ("cy", pa.float64())]))

    return images.select("chart_id", "width", "height", "data").join(boxes, "chart_id").mapInArrow(run, "chart_id long, kind string, ordinal int, text string, cx double, cy double")


def labels_of(texts: DataFrame) -> DataFrame:
    """chart_id, title, x_label, y_label from extracted texts."""
    at = lambda k: F.max(F.when(F.col("kind") == k, F.col("text"))).alias(k)
    return texts.groupBy("chart_id").agg(at("title"), at("x_label"), at("y_label"))


def confuse(text: Column, rate: int = 3, seed: int = 0) -> Column:
    """What a reader confuses: in one of ``rate`` texts l, I, 1 and O, 0 are taken for each other."""
    return F.when(draw(text, "confuse", seed) % rate == 0, F.translate(text, "lI1O0oS5", "1lI0Oc5S")).otherwise(text)
