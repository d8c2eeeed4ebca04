"""From pixels to series colours: cleaning, colour histogram, weighted k-means, knee and choice of k, background, ranges."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.color import full_hue, np_full_hue, np_hsv, with_hsv

#: Defaults (fixed values of the method): largest k, share of the error that a k must explain, half-widths of ranges.
K_MAX, EXPLAINED, SATURATION = 8, 0.985, 64
WIDTHS = (10, 25, 40)
#: Distinct colours up to which k-means is solved exactly.
EXACT = 6
_HIST = "chart_id long, cells array<struct<r:int,g:int,b:int,w:long>>"


def saturate(px: DataFrame, threshold: int = SATURATION, background: str = "white", enabled: bool = True) -> DataFrame:
    """Pixels above the saturation threshold keep their hue at full saturation and value; all grays become background."""
    if not enabled:
        return px
    keep = [c for c in px.columns if c not in ("r", "g", "b", "h", "s", "v")]
    h = with_hsv(px)
    fr, fg, fb = full_hue(F.col("h"))
    gone = 255 if background == "white" else 0
    on = F.col("s") > threshold
    return h.select(*keep, *(F.when(on, c).otherwise(gone).cast("int").alias(n) for n, c in zip("rgb", (fr, fg, fb))))


def cleaned_colours(px: DataFrame, threshold: int = SATURATION, background: int = 255) -> DataFrame:
    """chart_id, r, g, b, w of every distinct colour of a chart, the cleaned colour cr, cg, cb and its h, s, v.

    A colour is cleaned and measured once however many pixels have it; each step is a lookup on the step before, so the
    generated code stays small.
    """
    of = px.groupBy("chart_id", "r", "g", "b").agg(F.count("*").alias("w"))
    clean = saturate(of.select("chart_id", "w", F.col("r").alias("r0"), F.col("g").alias("g0"), F.col("b").alias("b0"), "r", "g", "b"), threshold, "white" if background == 255 else "black")
    return clean.select("chart_id", F.col("r0").alias("r"), F.col("g0").alias("g"), F.col("b0").alias("b"), "w", F.col("r").alias("cr"), F.col("g").alias("cg"), F.col("b").alias("cb"))


def masks_by_colour(px: DataFrame, of: DataFrame, boxes: DataFrame) -> DataFrame:
    """``masks`` of raw pixels and their ``cleaned_colours``."""
    c = with_hsv(of.select("chart_id", F.struct("r", "g", "b").alias("raw"), F.col("cr").alias("r"), F.col("cg").alias("g"), F.col("cb").alias("b")))
    inside = F.col("h").between(F.col("hlo"), F.col("hhi")) & F.col("s").between(F.col("slo"), F.col("shi")) & F.col("v").between(F.col("vlo"), F.col("vhi"))
    own = c.join(boxes, "chart_id").filter(inside).select("chart_id", "series_no", "raw.r", "raw.g", "raw.b").distinct()
    return px.join(own, ["chart_id", "r", "g", "b"]).select("chart_id", "series_no", "px", "py")


def histogram(px: DataFrame, pixels: int, background: tuple[int, int, int] = (255, 255, 255)) -> DataFrame:
    """chart_id, r, g, b, w of sparse ink (pixels, or colours with their number ``w``); pixels without ink count as background, so the weights of a chart sum to ``pixels``."""
    got = px.groupBy("chart_id", "r", "g", "b").agg((F.sum("w") if "w" in px.columns else F.count("*")).alias("w"))
    rest = got.groupBy("chart_id").agg((F.lit(pixels) - F.sum("w")).alias("w")).select("chart_id", *(F.lit(c).alias(n) for c, n in zip(background, "rgb")), "w")
    return got.unionByName(rest).groupBy("chart_id", "r", "g", "b").agg(F.sum("w").cast("long").alias("w"))


def cells(hist: DataFrame) -> DataFrame:
    """One row per chart with its histogram as an array, heaviest first; after cleaning 1531 cells at most."""
    item = F.struct((-F.col("w")).alias("n"), "r", "g", "b")
    got = hist.groupBy("chart_id").agg(F.sort_array(F.collect_list(item)).alias("c"))
    return got.select("chart_id", F.transform("c", lambda x: F.struct(x["r"].cast("int").alias("r"), x["g"].cast("int").alias("g"), x["b"].cast("int").alias("b"), (-x["n"]).cast("long").alias("w"))).alias("cells"))


def distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Squared distances, centre by centre: memory of a few columns for any number of colours."""
    return np.stack([((x - one) ** 2).sum(axis=1) for one in c], axis=1)


def _groupings(n: int) -> list[tuple[int, ...]]:
    """Every way to group n things, as labels in order of first use."""
    out: list[tuple[int, ...]] = [()]
    for _ in range(n):
        out = [(*g, j) for g in out for j in range(max(g, default=-1) + 2)]
    return out


def fit(x: np.ndarray, w: np.ndarray, k: int, rounds: int = 25) -> tuple[np.ndarray, np.ndarray, float]:
    """Weighted k-means; x sorted heaviest first.

    Cleaned hues lie equally far from white and from each other, where Lloyd's rule stops at ties, so up to ``EXACT``
    colours the best of all groupings is taken. More are fitted by Lloyd from a farthest-first start, ties to the lower centre.
    """
    if len(x) <= EXACT:
        best = None
        for g in _groupings(len(x)):
            if max(g) + 1 == min(k, len(x)):
                own = np.array(g)
                total = np.bincount(own, weights=w)
                c = np.stack([np.bincount(own, weights=w * x[:, i]) / total for i in range(3)], axis=1)
                e = float((((x - c[own]) ** 2).sum(axis=1) * w).sum())
                if best is None or e < best[2] - 1e-9:
                    best = (c, own, e)
        return best
    at = [0]
    near = ((x - x[0]) ** 2).sum(axis=1)
    for _ in range(1, min(k, len(x))):
        at.append(int(near.argmax()))
        near = np.minimum(near, ((x - x[at[-1]]) ** 2).sum(axis=1))
    c = x[at].astype(float)
    own = None
    for _ in range(rounds):
        new = distances(x, c).argmin(axis=1)
        if own is not None and (new == own).all():
            break
        own = new
        for j in range(len(c)):
            if (own == j).any():
                c[j] = np.average(x[own == j], axis=0, weights=w[own == j])
    own = distances(x, c).argmin(axis=1)
    return c, own, float((((x - c[own]) ** 2).sum(axis=1) * w).sum())


def sweep(x: np.ndarray, w: np.ndarray, k_max: int = K_MAX) -> tuple[list[float], list]:
    """Squared errors for k = 1..k_max and the fits; once the error is zero larger k are not fitted."""
    errors, fits = [], []
    for k in range(1, k_max + 1):
        if errors and errors[-1] <= 1e-9:
            errors.append(0.0)
            fits.append(fits[-1])
            continue
        c, own, e = fit(x, w, k)
        errors.append(min(e, errors[-1]) if errors else e)
        fits.append((c, own))
    return errors, fits


def curve(errors: list[float], norm: str = "explained") -> list[float]:
    """The error curve as explained share, residual share or scaled to its own range."""
    first = errors[0]
    if first <= 0:
        return [1.0] * len(errors) if norm == "explained" else [0.0] * len(errors)
    if norm == "residual":
        return [e / first for e in errors]
    if norm == "minmax":
        low, span = min(errors), max(errors) - min(errors)
        return [1 - (e - low) / span for e in errors]
    return [1 - e / first for e in errors]


def knee(values: list[float], sensitivity: float = 1.0) -> int:
    """k of the first confirmed local maximum of the scaled curve above its diagonal; else of the highest; 1 if flat."""
    n = len(values)
    lo, hi = min(values), max(values)
    if hi - lo < 1e-12:
        return 1
    d = [(v - lo) / (hi - lo) - i / (n - 1) for i, v in enumerate(values)]
    peaks = [i for i in range(1, n - 1) if d[i] >= d[i - 1] and d[i] >= d[i + 1]]
    for a, b in zip(peaks, [*peaks[1:], n]):
        if any(d[j] < d[a] - sensitivity / (n - 1) for j in range(a + 1, b)):
            return a + 1
    return d.index(max(d)) + 1


def chosen(errors: list[float], rule: str = "corrected", norm: str = "explained", threshold: float = EXPLAINED) -> int:
    """k by rule: ``knee``, ``corrected`` (+1 once if too little is explained), ``repeat`` (+1 until enough is)."""
    share = curve(errors, "explained")
    k = knee([-v for v in curve(errors, norm)] if norm == "residual" else curve(errors, norm))
    if rule == "listing_on_residual":  # the printed comparison applied to the residual share: an ablation
        return min(len(errors), k + 1) if curve(errors, "residual")[k - 1] < threshold else k
    if errors[0] <= 0 or rule == "knee":
        return k
    enough = (lambda i: 1 - share[i - 1] <= 1 - threshold) if norm == "residual" else (lambda i: share[i - 1] >= threshold)
    while k < len(errors) and not enough(k):
        k += 1
        if rule == "corrected":
            break
    return k


def select_k(hist: DataFrame, rules: tuple[str, ...] = ("corrected",), norm: str = "explained", k_max: int = K_MAX, threshold: float = EXPLAINED) -> DataFrame:
    """chart_id, curve, one k per rule (k_<rule>), centers of the first rule's k; all rules share one sweep."""
    kinds = "chart_id long, colours int, errors array<double>, " + ", ".join(f"k_{r} int" for r in rules) + ", centers array<struct<cid:int,r:double,g:double,b:double,w:long>>"

    def run(batches):
        for batch in batches:
            rows = []
            for chart, cell in zip(batch.column("chart_id").to_pylist(), batch.column("cells").to_pylist()):
                x, w = np.array([[c["r"], c["g"], c["b"]] for c in cell], float), np.array([c["w"] for c in cell], float)
                x, w = x[w > 0], w[w > 0]
                errors, fits = sweep(x, w, k_max)
                ks = [chosen(errors, r, norm, threshold) for r in rules]
                c, own = fits[ks[0] - 1]
                found = [{"cid": j, "r": float(c[j][0]), "g": float(c[j][1]), "b": float(c[j][2]), "w": int(w[own == j].sum())} for j in range(len(c))]
                rows.append({"chart_id": chart, "colours": len(x), "errors": errors, **{f"k_{r}": k for r, k in zip(rules, ks)}, "centers": found})
            if rows:
                yield pa.RecordBatch.from_pylist(rows, schema=_arrow(rules))

    return cells(hist).mapInArrow(run, kinds)


def _arrow(rules) -> pa.Schema:
    centre = pa.struct([("cid", pa.int32()), ("r", pa.float64()), ("g", pa.float64()), ("b", pa.float64()), ("w", pa.int64())])
    return pa.schema([("chart_id", pa.int64()), ("colours", pa.int32()), ("errors", pa.list_(pa.float64())), *((f"k_{r}", pa.int32()) for r in rules), ("centers", pa.list_(centre))])


def knee_column(values: Column, n: int = K_MAX, sensitivity: float = 1.0) -> Column:
    """``knee`` of an array column inside the JVM."""
    lo, hi = F.array_min(values), F.array_max(values)
    d = F.transform(values, lambda v, i: (v - lo) / (hi - lo) - i / F.lit(float(n - 1)))
    get = lambda a, i: F.get(a, i)
    peaks = lambda a: F.filter(F.sequence(F.lit(1), F.lit(n - 2)), lambda i: (get(a, i) >= get(a, i - 1)) & (get(a, i) >= get(a, i + 1)))
    nxt = lambda a, i: F.coalesce(F.array_min(F.filter(peaks(a), lambda j: j > i)), F.lit(n))
    sure = F.filter(peaks(d), lambda i: F.exists(F.sequence(F.lit(0), F.lit(n - 1)), lambda j: (j > i) & (j < nxt(d, i)) & (get(d, j) < get(d, i) - sensitivity / (n - 1))))
    return F.when(hi - lo < 1e-12, 1).otherwise(F.coalesce(F.get(sure, F.lit(0)) + 1, F.array_position(d, F.array_max(d)).cast("int")))


def drop_background(centers: DataFrame) -> DataFrame:
    """chart_id, series_no, r, g, b, w: all clusters but the one of most pixels, heaviest first."""
    flat = centers.select("chart_id", F.explode("centers").alias("c")).select("chart_id", "c.*")
    return _foreground(flat)


def _foreground(flat: DataFrame) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("chart_id").orderBy(F.desc("w"), "cid"))
    out = flat.withColumn("_n", rank).filter("_n > 1")
    return out.select("chart_id", (F.col("_n") - 1).alias("series_no"), *(F.round(c).cast("int").alias(c) for c in "rgb"), "w")


def exact_clusters(hist: DataFrame) -> DataFrame:
    """chart_id, cid, r, g, b, w: every colour its own cluster, as k-means ends on cleaned charts with k = colours."""
    rank = F.row_number().over(Window.partitionBy("chart_id").orderBy(F.desc("w"), "r", "g", "b")) - 1
    return hist.filter("w > 0").withColumn("cid", rank)


def assign(points: DataFrame, centers: DataFrame) -> DataFrame:
    """Nearest centre of every colour by squared distance, ties to the lower id; centers is a handful of rows per chart."""
    c = centers.select("chart_id", "cid", F.col("r").alias("cr"), F.col("g").alias("cg"), F.col("b").alias("cb"))
    d = (F.col("r") - F.col("cr")) ** 2 + (F.col("g") - F.col("cg")) ** 2 + (F.col("b") - F.col("cb")) ** 2
    return points.join(c, "chart_id").groupBy("chart_id", "r", "g", "b", "w").agg(F.min(F.struct(d.cast("long").alias("d"), "cid")).alias("m")).select("chart_id", "r", "g", "b", "w", F.col("m.cid").alias("cid"), F.col("m.d").alias("d2"))


def ranges(colours: DataFrame, widths: tuple[int, int, int] = WIDTHS, bounds: str = "clamped") -> DataFrame:
    """chart_id, series_no, part, hlo, hhi, slo, shi, vlo, vhi: one box per colour, two where hue wraps.

    ``bounds="literal"`` takes the printed formula, whose lower bound is never above zero: an ablation that selects too much.
    """
    dh, ds, dv = widths
    c = with_hsv(colours.select("chart_id", "series_no", *"rgb"))
    lo = lambda n, d: F.least(F.lit(0), F.col(n) - d) if bounds == "literal" else F.greatest(F.lit(0), F.col(n) - d)
    hi = lambda n, d, top: F.greatest(F.lit(top), F.col(n) + d) if bounds == "literal" else F.least(F.lit(top), F.col(n) + d)
    main = F.struct(F.lit(1).alias("part"), lo("h", dh).alias("hlo"), hi("h", dh, 180).alias("hhi"))
    wrap = F.when(F.col("h") < dh, F.struct(F.lit(2).alias("part"), (F.col("h") - dh + 180).alias("hlo"), F.lit(180).alias("hhi"))).when(F.col("h") + dh > 180, F.struct(F.lit(2).alias("part"), F.lit(0).alias("hlo"), (F.col("h") + dh - 180).alias("hhi")))
    box = c.select("chart_id", "series_no", F.explode(F.filter(F.array(main, wrap), lambda x: x.isNotNull())).alias("x"), lo("s", ds).alias("slo"), hi("s", ds, 255).alias("shi"), lo("v", dv).alias("vlo"), hi("v", dv, 255).alias("vhi"))
    return box.select("chart_id", "series_no", F.col("x.part").alias("part"), F.col("x.hlo").cast("int").alias("hlo"), F.col("x.hhi").cast("int").alias("hhi"), "slo", "shi", "vlo", "vhi")


def masks(px: DataFrame, boxes: DataFrame) -> DataFrame:
    """chart_id, series_no, px, py: pixels in a series' range or ranges; a pixel may belong to several series."""
    colours = with_hsv(px.select("chart_id", "r", "g", "b").distinct())  # ranges meet colours, not pixels
    inside = F.col("h").between(F.col("hlo"), F.col("hhi")) & F.col("s").between(F.col("slo"), F.col("shi")) & F.col("v").between(F.col("vlo"), F.col("vhi"))
    of = colours.join(boxes, "chart_id").filter(inside).select("chart_id", "series_no", "r", "g", "b").distinct()
    return px.select("chart_id", "px", "py", "r", "g", "b").join(of, ["chart_id", "r", "g", "b"]).select("chart_id", "series_no", "px", "py")


def column_points(mask: DataFrame) -> DataFrame:
    """A mask as points of one series: x is the column, y the (doubled, upward) mean row of its ink, in whole numbers."""
    rows = mask.groupBy("chart_id", "series_no", "px").agg(F.sum("py").alias("s"), F.count("*").alias("n"))
    return rows.select("chart_id", F.col("series_no").cast("string").alias("series_key"), F.col("px").cast("long").alias("x"), (-F.floor(F.col("s") * 1000 / F.col("n"))).cast("long").alias("y"))


# The packed form: one numpy image at a time, nothing exploded to rows.


def np_saturate(img: np.ndarray, threshold: int = SATURATION, background: int = 255) -> np.ndarray:
    """Cleaned copy of an H x W x 3 image."""
    hsv = np_hsv(img)
    return np.where((hsv[..., 1] > threshold)[..., None], np_full_hue(hsv[..., 0]), background).astype(np.uint8)


def np_histogram(img: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct colours, heaviest first (ties by r, g, b), and their pixel counts."""
    code = img.reshape(-1, 3).astype(np.int64) @ np.array([65536, 256, 1])
    key, n = np.unique(code, return_counts=True)
    at = np.lexsort((key, -n))
    return np.stack((key // 65536, key // 256 % 256, key % 256), axis=1)[at].astype(float), n[at].astype(float)


def np_boxes(rgb: np.ndarray, widths: tuple[int, int, int] = WIDTHS) -> list[list[tuple[int, ...]]]:
    """HSV boxes of each colour."""
    out = []
    for h, s, v in np_hsv(np.asarray(rgb)).tolist():
        rest = (max(0, s - widths[1]), min(255, s + widths[1]), max(0, v - widths[2]), min(255, v + widths[2]))
        box = [(max(0, h - widths[0]), min(180, h + widths[0]), *rest)]
        if h < widths[0]:
            box.append((h - widths[0] + 180, 180, *rest))
        elif h + widths[0] > 180:
            box.append((0, h + widths[0] - 180, *rest))
        out.append(box)
    return out


def np_mask(hsv: np.ndarray, boxes: list[tuple[int, ...]]) -> np.ndarray:
    h, s, v = hsv[..., 0], hsv[..., 1], hsv[..., 2]
    out = np.zeros(h.shape, bool)
    for a, b, c, d, e, f in boxes:
        out |= (h >= a) & (h <= b) & (s >= c) & (s <= d) & (v >= e) & (v <= f)
    return out


def np_distinct(img: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct colours of an image, their pixel counts, and which of them every pixel has. The corner's colour, mostly the background, is not sorted."""
    flat = img.reshape(-1, 3).astype(np.int32)
    code = flat[:, 0] << 16 | flat[:, 1] << 8 | flat[:, 2]
    other = np.flatnonzero(code != code[0])
    key, at, n = np.unique(code[other], return_inverse=True, return_counts=True)
    which = np.zeros(len(code), np.int64)
    which[other] = at + 1
    key = np.concatenate((code[:1], key))
    return np.stack((key >> 16, key >> 8 & 255, key & 255), axis=1).astype(np.uint8), np.concatenate(([len(code) - len(other)], n)), which


def np_series(img: np.ndarray, rule: str = "corrected", threshold: int = SATURATION, clean: bool = True, widths: tuple[int, int, int] = WIDTHS, least_ink: int = 3) -> tuple[int, list[tuple[tuple[int, int, int], np.ndarray]]]:
    """k, and the colour and mask of every series of one image: the whole chain from pixels to single-series images."""
    raw, many, which = np_distinct(img)  # a colour is cleaned and measured once however many pixels have it
    use = np_saturate(raw, threshold) if clean else raw
    code, at = np.unique(use.astype(np.int64) @ np.array([65536, 256, 1]), return_inverse=True)
    n = np.bincount(at, weights=many)
    heavy = np.lexsort((code, -n))
    x, w = np.stack((code // 65536, code // 256 % 256, code % 256), axis=1)[heavy].astype(float), n[heavy]
    errors, fits = sweep(x, w)
    k = chosen(errors, rule)
    c, own = fits[k - 1]
    weight = np.array([w[own == j].sum() for j in range(len(c))])
    order = [j for j in np.argsort(-weight, kind="stable").tolist() if weight[j] > 0][1:]
    colours = np.rint(c[order]).astype(int)
    hsv = np_hsv(use)
    found = []
    for rgb, box in zip(colours.tolist(), np_boxes(colours, widths) if len(colours) else []):
        mask = np_mask(hsv, box)[which].reshape(img.shape[:2])
        if mask.sum() >= least_ink:
            found.append((tuple(rgb), mask))
    return k, found
