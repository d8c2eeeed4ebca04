"""The experiment workloads on the given tables; every one returns (workload, corpus, metric, n, value) rows unless noted."""

from __future__ import annotations

import functools

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.draws import draw
from ..operators import baseline, cluster, learned, legend, measure, raster, synth, text, truth
from ..sources.families import FAMILIES, trend
from ..sources.tables import image_batches, stored
from .queries import QUERIES, eligible

RESULT = ("workload", "corpus", "metric", "n", "value")


def held(df: DataFrame) -> DataFrame:
    """``df`` computed once: stored in the shared folder, so that the plans made on it stay small on the driver and in every task."""
    return stored(df)


def query(f):
    """Registers a workload whose result SQL cannot express."""
    @functools.wraps(f)
    def run(spark, d):
        image_batches(spark)
        return f(spark, d)

    QUERIES[f.__name__] = run
    return run


def scored(df: DataFrame, workload: str, corpus: str, metric: str | None = None) -> DataFrame:
    """A measure's row with its workload and corpus."""
    name = F.lit(metric) if metric else F.col("metric")
    return df.select(F.lit(workload).alias("workload"), F.lit(corpus).alias("corpus"), name.alias("metric"), F.col("n").cast("long").alias("n"), F.col("value").cast("double").alias("value"))


def union(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def balanced_points(spark: SparkSession, d: str, family: str = "supplier", seed: int = 0) -> DataFrame:
    """A family whose classes a drawn slope balances."""
    return trend(FAMILIES[family](spark, d), seed).drop("slope")


def first_charts(points: DataFrame, n: int, seed: int = 0, skip: int = 0) -> DataFrame:
    """Points of the ``n`` charts of smallest draw behind the first ``skip``; only ids are sorted, and only the first kept."""
    ids = points.select("chart_id").distinct().select("chart_id", draw(F.col("chart_id"), "sample", seed).alias("_u"))
    first = ids.orderBy("_u", "chart_id").limit(skip + n)
    if skip:
        first = first.withColumn("_n", F.row_number().over(Window.orderBy("_u", "chart_id"))).filter(F.col("_n") > skip)
    return points.join(F.broadcast(first.select("chart_id")), "chart_id", "left_semi")


def charts_behind(points: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """Points of all charts but the ``n`` of smallest draw, which are left to training."""
    return points.join(F.broadcast(first_charts(points, n, seed).select("chart_id").distinct()), "chart_id", "left_anti")


def true_series(points: DataFrame, palette: str = "rgb3") -> DataFrame:
    """Relation, colour, number and legend label of every series."""
    named = synth.coloured(points, palette)
    label = synth.random_label(F.concat_ws("|", "chart_id", "series_key"), "legend", 3, 9)
    return truth.relations(points).join(named, ["chart_id", "series_key"]).withColumn("series_label", label)


def rendered(points: DataFrame, palette: str = "rgb3", plot_type: str = "line", noise: int = 0, style: str = "plain", blur: bool = False) -> DataFrame:
    """Packed images; ``plot_type="mixed"`` and ``style="diverse"`` let each chart draw its own."""
    colours = synth.coloured(points, palette)
    if plot_type != "mixed" and style == "plain":
        px = raster.ink(points, colours, plot_type)
        px = raster.degraded(held(px), noise) if noise else px  # speckles meet the ink they are cast by
    else:
        fixed = ({} if plot_type == "mixed" else {"plot_type": plot_type}) | ({} if style == "diverse" else {"style": style})
        px = held(raster.styled_ink(points, held(colours), held(synth.styles(points, fixed, "diverse").select("chart_id", "plot_type", "style"))))
        px = raster.degraded(px, noise) if noise else px
    return raster.packed(px, blur=blur)


def steady(points: DataFrame, least: int = 4) -> DataFrame:
    """Points of charts all of whose series have ``least`` points."""
    ok = points.groupBy("chart_id", "series_key").agg(F.count("*").alias("k")).groupBy("chart_id").agg(F.min("k").alias("k")).filter(F.col("k") >= least).select("chart_id")
    return points.join(ok, "chart_id", "left_semi")


def training_points(spark: SparkSession, d: str, seed: int = 2) -> DataFrame:
    """Charts of one to three series for training and control: users, nations and brands, none of which the tests of the plain format use."""
    pool = [FAMILIES[f](spark, d).select((F.col("chart_id") + 1_000_000 * k).alias("chart_id"), "series_key", "x", "y") for k, f in enumerate(("user", "nation", "brand"), 1)]
    points = union(pool)
    first = points.select("chart_id", "series_key").distinct().withColumn("_k", F.row_number().over(Window.partitionBy("chart_id").orderBy("series_key"))).filter("_k <= 3").drop("_k")
    return trend(points.join(first, ["chart_id", "series_key"], "left_semi"), seed).drop("slope")


def model_for(points: DataFrame, n: int = 100, palette: str = "rgb3", plot_type: str = "mixed", epochs: int = 25, seed: int = 0, noise: int = 0, skip: int = 0, start=None, style: str = "plain"):
    """A classifier of ``n`` rendered charts: one half trains, the other picks the epoch; its score there is ``validation``."""
    use = held(first_charts(points, n, seed, skip))
    return learned.train(learned.examples(rendered(use, palette, plot_type, noise, style), held(true_series(use, palette))), start, epochs, seed, validate=True)


def validation(points: DataFrame, model, workload: str, corpus: str, n: int) -> DataFrame:
    """The score that a model reached on its validation half, as a row."""
    row = points.sparkSession.range(1).select(F.lit("validation").alias("metric"), F.lit(n).alias("n"), F.lit(round(getattr(model, "validation", 0.0), 6)).alias("value"))
    return scored(row, workload, corpus)


def accuracy(pred: DataFrame, true: DataFrame, workload: str, corpus: str) -> DataFrame:
    return scored(measure.series_no_ocr(pred, true), workload, corpus).unionByName(scored(measure.raw(pred, true), workload, corpus))


@query
def synthetic_end_to_end(spark, d):
    """A hundred charts of the training format, unseen, behind the hundred that train: images in, axis labels, series labels and relations out, scored by all four measures."""
    points = held(training_points(spark, d))
    model = model_for(points, 100, seed=1)
    test = held(first_charts(points, 100, 1, 100))
    return _end_to_end(test, model, "synthetic_end_to_end", {"synthetic": "layout"}, plot_type="mixed").unionByName(validation(points, model, "synthetic_end_to_end", "training", 50))


def _end_to_end(points: DataFrame, model, workload: str, detectors: dict[str, str], rotate: str = "manual", ssd=None, plot_type: str = "line") -> DataFrame:
    """The five measures for every corpus and its detector; ``points`` are stored. Images, relations and colour keys, which no detector changes, are found once."""
    true = held(true_series(points))
    labels = held(synth.styles(points).select("chart_id", "title", "x_label", "y_label", *text.PLACES))
    images, facets = text.annotated(rendered(points, plot_type=plot_type), labels, true, held)
    area = held(plot_series(images, model))
    keys = held(legend_keys(images, area))
    rows = []
    for corpus, detector in detectors.items():
        found = facets.select("chart_id", "kind", "ordinal", "x0", "y0", "x1", "y1") if detector == "truth" else text.detect(images, detector, ssd)
        texts = held(text.extract(images, found, rotate))
        pred = held(labelled(area, keys, texts))
        axis, series = held(measure.axis(text.labels_of(texts), labels)), held(measure.series(pred, true))
        rows += [scored(m, workload, corpus) for m in (axis, series, measure.total(axis, series), measure.series_no_ocr(pred, true), measure.raw(pred, true))]
    return union(rows)


def plot_series(images: DataFrame, model=None) -> DataFrame:
    """What ``learned.predict`` finds in the plot area of annotated images."""
    return learned.predict(crop(images, 12, 12, raster.W, raster.H), model)


def extract(images: DataFrame, texts: DataFrame, model=None) -> DataFrame:
    """chart_id, series_no, series_label, r, g, b, relation: series of annotated images, labelled by the nearest legend text.

    Relations come from the plot area alone, colours of the keys from the legend area; both are found in the packed image.
    """
    area = plot_series(images, model)
    return labelled(area, legend_keys(images, area), texts)


def labelled(area: DataFrame, keys: DataFrame, texts: DataFrame) -> DataFrame:
    """The same from the series of the plot area and the pixels of their keys."""
    entries = texts.filter("kind = 'legend_text'").select("chart_id", "ordinal", "text", F.col("cx"), F.col("cy"))
    by = legend.assign(entries, keys, "median")
    best = by.groupBy("chart_id", "series_no").agg(F.min_by("text", F.struct("d2", "ordinal")).alias("series_label"))
    return area.select("chart_id", "series_no", "r", "g", "b", "relation").join(best, ["chart_id", "series_no"], "left").withColumn("series_label", F.coalesce("series_label", F.lit("")))


def crop(images: DataFrame, x: int, y: int, w: int, h: int, right: int = raster.LEFT + raster.IW + 6) -> DataFrame:
    """The same window of every image; columns from ``right`` on, where colour keys of the legend may stand, are set to the corner's colour."""
    import pyarrow as pa

    def cut(ww: int, hh: int, data: bytes) -> bytes:
        out = np.frombuffer(data, np.uint8).reshape(hh, ww, 3)[y : y + h, x : x + w].copy()
        out[:, right:] = out[0, 0]
        return out.tobytes()

    def run(batches):
        for batch in batches:
            out = [cut(*r) for r in zip(*(batch.column(n).to_pylist() for n in ("width", "height", "data")))]
            n = len(out)
            yield pa.RecordBatch.from_arrays([batch.column("chart_id"), pa.array([w] * n, pa.int32()), pa.array([h] * n, pa.int32()), pa.array([3] * n, pa.int32()), pa.array(out, pa.binary())], names=["chart_id", "width", "height", "channels", "data"])

    return images.select("chart_id", "width", "height", "data").mapInArrow(run, "chart_id long, width int, height int, channels int, data binary")


def legend_keys(images: DataFrame, series: DataFrame) -> DataFrame:
    """chart_id, series_no, px, py: pixels right of the plot whose hue is a series' hue."""
    import pyarrow as pa

    s = series.groupBy("chart_id").agg(F.collect_list(F.struct("series_no", "r", "g", "b")).alias("s"))

    def run(batches):
        for batch in batches:
            rows = []
            for c, w, h, data, found in zip(*(batch.column(n).to_pylist() for n in ("chart_id", "width", "height", "data", "s"))):
                hsv = cluster.np_hsv(cluster.np_saturate(np.frombuffer(data, np.uint8).reshape(h, w, 3)[:, raster.W :]))
                for e in found:
                    mask = cluster.np_mask(hsv, cluster.np_boxes(np.array([[e["r"], e["g"], e["b"]]]))[0])
                    rows += [{"chart_id": c, "series_no": e["series_no"], "px": int(x) + raster.W, "py": int(y)} for y, x in zip(*np.nonzero(mask))]
            if rows:
                yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("chart_id", pa.int64()), ("series_no", pa.int32()), ("px", pa.int32()), ("py", pa.int32())]))

    return images.select("chart_id", "width", "height", "data").join(s, "chart_id").mapInArrow(run, "chart_id long, series_no int, px int, py int")


@query
def without_boundary(spark, d):
    """The same charts scored on all series and without those near the cut."""
    points = balanced_points(spark, d, "supplier", 1)
    test = first_charts(points, 100, 5)
    true, rho = true_series(test), truth.spearman(test)
    pred = held(learned.predict(rendered(test)))
    clear = measure.without_boundary(true, rho, "series")
    return union([accuracy(pred, true, "without_boundary", "all"), scored(measure.series_no_ocr(pred, clear), "without_boundary", "clear_series"), scored(measure.series_no_ocr(pred, measure.without_boundary(true, rho)), "without_boundary", "clear_charts")])


def _versus(points: DataFrame, workload: str, plot_type: str) -> DataFrame:
    colours = synth.coloured(points)
    true = true_series(points)
    px = raster.ink(points, colours, plot_type)
    ours = held(learned.predict(raster.packed(px)))
    theirs = held(baseline.point_extractor(px, true, plot_type=plot_type))
    rows = [accuracy(ours, true, workload, "ours"), accuracy(theirs, true, workload, "point_extractor" if plot_type == "bar" else "mean_trace")]
    if plot_type == "line":  # the extractor proper: line by line, so that it can be right where lines stay apart
        rows.append(scored(measure.raw(baseline.line_extractor(px), true), workload, "point_extractor"))
    return union(rows)


@query
def compare_lines(spark, d):
    """Line charts of one to three series against the point extractor, which sees no colours."""
    return _versus(first_charts(steady(balanced_points(spark, d, "customer_status", 6)), 100), "compare_lines", "line")


@query
def compare_single_bars(spark, d):
    """Bar charts of one series against the point extractor."""
    return _versus(first_charts(FAMILIES["customer"](spark, d), 100), "compare_single_bars", "bar")


def web_points(spark: SparkSession, d: str) -> DataFrame:
    """A mixed pool standing for collected charts: users with all five or three of their types, brands, nations."""
    user = FAMILIES["user"](spark, d)
    w = Window.partitionBy("chart_id").orderBy("series_key")
    key = user.select("chart_id", "series_key").distinct().withColumn("_k", F.row_number().over(w))
    narrow = user.join(key, ["chart_id", "series_key"]).filter((F.col("chart_id") % 4 == 0) | (F.col("_k") <= 3)).drop("_k")
    shift = lambda df, k: df.select((F.col("chart_id") + k).alias("chart_id"), "series_key", "x", "y")
    return trend(union([shift(narrow, 1_000_000), shift(FAMILIES["brand"](spark, d), 2_000_000), shift(FAMILIES["nation"](spark, d), 3_000_000)]), 4).drop("slope")


def hardness(points: DataFrame) -> DataFrame:
    """chart_id, hardness: hard with over three series, a series near the cut, or 30 % of its ink shared."""
    near = measure.boundary(truth.spearman(points)).select("chart_id").distinct().withColumn("near", F.lit(1))
    many = points.groupBy("chart_id").agg(F.count_distinct("series_key").alias("k"))
    numbered = points.join(synth.coloured(points, "wide").select("chart_id", "series_key", "series_no"), ["chart_id", "series_key"])
    per = raster.line(numbered).groupBy("chart_id", "px", "py").agg(F.count("*").alias("m"))
    shared = per.groupBy("chart_id").agg((F.avg((F.col("m") > 1).cast("double"))).alias("shared"))
    hard = (F.col("k") > 3) | F.col("near").isNotNull() | (F.col("shared") > 0.3)
    return many.join(near, "chart_id", "left").join(shared, "chart_id", "left").select("chart_id", F.when(hard, "hard").otherwise("easy").alias("hardness"))


@query
def web_like(spark, d):
    """Fifty noisy charts of diverse colours: accuracy of easy and hard ones and in total."""
    points = first_charts(web_points(spark, d), 50)
    true = true_series(points, "wide")
    pred = held(learned.predict(rendered(points, "wide", "mixed", noise=40)))
    per = measure.per_chart_no_ocr(pred, true).join(hardness(points), "chart_id")
    s = measure.strata(per, "hardness")
    return s.select(F.lit("web_like").alias("workload"), F.coalesce("hardness", F.lit("total")).alias("corpus"), F.lit("series_no_ocr").alias("metric"), F.col("n").cast("long").alias("n"), "value")


@query
def web_like_causes(spark, d):
    """The same charts where axes are coloured, and with those charts left out."""
    points = first_charts(web_points(spark, d), 50)
    true = true_series(points, "wide")
    px = raster.ink(points, synth.coloured(points, "wide"), "line")
    axes = points.select("chart_id").distinct().filter(F.col("chart_id") % 5 == 0)
    bars = axes.select("chart_id", F.explode(F.sequence(F.lit(raster.TOP), F.lit(raster.TOP + raster.IH))).alias("py"), F.lit(raster.LEFT - 4).alias("px")).select("chart_id", F.explode(F.array(F.col("px"), F.col("px") + 1, F.col("px") + 2)).alias("px"), "py", F.lit(None).cast("int").alias("series_no"), F.lit(120).alias("r"), F.lit(20).alias("g"), F.lit(230).alias("b"))
    pred = held(learned.predict(raster.packed(px.unionByName(bars))))
    rest = true.join(axes, "chart_id", "left_anti")
    return union([accuracy(pred, true, "web_like_causes", "all"), accuracy(pred.join(axes, "chart_id", "left_anti"), rest, "web_like_causes", "plain_axes")])


@query
def filtered_corpus(spark, d):
    """Charts that pass the corpus filter, by line rendering in wide colours."""
    points = FAMILIES["supplier"](spark, d)
    use = points.join(eligible(points), "chart_id", "left_semi")
    return accuracy(held(learned.predict(rendered(use, "drawn"))), true_series(use, "drawn"), "filtered_corpus", "qa_like")


@query
def all_corpora(spark, d):
    """Synthetic, web-like and filtered corpora side by side, and their total."""
    parts = []
    base = balanced_points(spark, d, "supplier", 1)
    raw = FAMILIES["supplier"](spark, d)
    for corpus, points, palette, noise, kind in (("synthetic", first_charts(base, 100, 5), "rgb3", 0, "mixed"), ("web_like", first_charts(web_points(spark, d), 50), "wide", 40, "mixed"), ("qa_like", raw.join(eligible(raw), "chart_id", "left_semi"), "drawn", 0, "line")):
        per = measure.per_chart_no_ocr(learned.predict(rendered(points, palette, kind, noise)), true_series(points, palette))
        parts.append(per.withColumn("corpus", F.lit(corpus)))
    s = measure.strata(union(parts), "corpus")
    return s.select(F.lit("all_corpora").alias("workload"), F.coalesce("corpus", F.lit("total")).alias("corpus"), F.lit("series_no_ocr").alias("metric"), F.col("n").cast("long").alias("n"), "value")


def _transfer(workload: str, model, control, test: DataFrame, control_test: DataFrame, **how) -> DataFrame:
    """Accuracy of the transferred and of the control model on their tests, chance, and both validation scores; ``how`` renders the tests."""
    rows, palette = [], how["palette"]
    for corpus, m, points in (("transfer", model, test), ("control", control, control_test)):
        rows.append(scored(measure.series_no_ocr(learned.predict(rendered(points, **how), m), true_series(points, palette)), workload, corpus))
        rows.append(validation(points, m, workload, corpus, 50))
    guess = baseline.random_guess(true_series(test, palette).drop("relation"))
    rows.append(scored(measure.series_no_ocr(guess, true_series(test, palette)), workload, "chance"))
    return union(rows)


def plain_model(spark: SparkSession, d: str, epochs: int = 20):
    """The model that is transferred: a hundred charts of all types in the default style."""
    return model_for(held(balanced_points(spark, d, "supplier", 3)), 100, epochs=epochs)


@query
def transfer_styles(spark, d):
    """A model of plain charts on a hundred of diverse styles, against one trained on another hundred of diverse styles, and chance."""
    diverse, n = training_points(spark, d, 4), 100
    control = model_for(diverse, n, "wide", noise=60, epochs=20, seed=1, style="diverse")
    test = held(first_charts(diverse, n, 1, n))
    return _transfer("transfer_styles", plain_model(spark, d), control, test, test, palette="wide", plot_type="mixed", noise=60, style="diverse")


@query
def transfer_web(spark, d):
    """The plain model on fifty web-like charts; the control learns from one half of them and is tested on the other."""
    web = held(first_charts(web_points(spark, d), 50))
    control = model_for(web, 25, "wide", noise=40, epochs=20)
    return _transfer("transfer_web", plain_model(spark, d), control, web, first_charts(web, 25, 0, 25), palette="wide", plot_type="mixed", noise=40)


@query
def transfer_corpus(spark, d):
    """The plain model on the first hundred filtered charts; the control learns from the second and is tested on the third."""
    points = steady(balanced_points(spark, d, "customer_status", 6), 2)
    ids = eligible(FAMILIES["customer_status"](spark, d))
    use = held(points.join(ids, "chart_id", "left_semi"))
    n = max(1, min(100, use.select("chart_id").distinct().count() // 3))  # a hundred each wherever the corpus has three hundred
    control = model_for(use, n, "drawn", "line", epochs=20, skip=n)
    return _transfer("transfer_corpus", plain_model(spark, d), control, first_charts(use, n), first_charts(use, n, 0, 2 * n), palette="drawn", plot_type="line")


@query
def rotation_ablation(spark, d):
    """Axis accuracy with the vertical label turned by us, tried four ways by the reader, or left as it is."""
    points = FAMILIES["supplier"](spark, d)
    labels = synth.styles(points).select("chart_id", "title", "x_label", "y_label", *text.PLACES)
    images, _ = text.annotated(rendered(points), labels, true_series(points))
    images = held(images)
    found = text.detect(images)
    return union([scored(measure.axis(text.labels_of(text.extract(images, found, m)), labels), "rotation_ablation", m) for m in ("manual", "auto", "none")])


@query
def facet_detection(spark, d):
    """Mean overlap of found and true boxes by detector, and axis accuracy that follows from each."""
    points = FAMILIES["supplier"](spark, d)
    labels = synth.styles(points).select("chart_id", "title", "x_label", "y_label", *text.PLACES)
    images, facets = text.annotated(rendered(points), labels, true_series(points))
    images, facets = held(images), held(facets)
    learn = max(1, min(40, points.select("chart_id").distinct().count() // 2))
    first = F.broadcast(first_charts(points, learn).select("chart_id").distinct())
    rows, ssd = [], trained_detector(images.join(first, "chart_id", "left_semi"), facets)
    test = images.join(first, "chart_id", "left_anti")
    boxes = facets.join(test.select("chart_id"), "chart_id", "left_semi")
    for name, found in (("layout", text.detect(test, "layout")), ("ssd", text.detect(test, "ssd", ssd)), ("truth", boxes)):
        rows.append(scored(box_overlap(found, boxes), "facet_detection", name, "mean_iou"))
        rows.append(scored(measure.axis(text.labels_of(text.extract(test, found)), labels.join(test.select("chart_id"), "chart_id", "left_semi")), "facet_detection", name))
    return union(rows)


def trained_detector(images: DataFrame, facets: DataFrame, most: int = 60) -> text.Detector:
    """The single-shot detector for at most ``most`` annotated images."""
    boxes = facets.groupBy("chart_id").agg(F.collect_list(F.struct("kind", "x0", "y0", "x1", "y1")).alias("f"))
    rows = images.join(boxes, "chart_id").orderBy("chart_id").limit(most).collect()
    shape = (rows[0]["height"], rows[0]["width"])
    return text.Detector(shape).train([np.frombuffer(r["data"], np.uint8).reshape(*shape, 3) for r in rows], [[tuple(f) for f in r["f"]] for r in rows])


def box_overlap(found: DataFrame, true: DataFrame) -> DataFrame:
    """n, value: mean over true boxes of the best intersection over union with a found box of its kind."""
    t = true.select("chart_id", "kind", "ordinal", *(F.col(c).alias(f"t{c}") for c in ("x0", "y0", "x1", "y1")))
    f = found.select("chart_id", "kind", "x0", "y0", "x1", "y1")
    j = t.join(f, ["chart_id", "kind"], "left")
    side = lambda a: F.greatest(F.lit(0), F.least(F.col(f"{a}1"), F.col(f"t{a}1")) - F.greatest(F.col(f"{a}0"), F.col(f"t{a}0")))
    both = side("x") * side("y")
    size = lambda p: (F.col(f"{p}x1") - F.col(f"{p}x0")) * (F.col(f"{p}y1") - F.col(f"{p}y0"))
    iou = F.coalesce(both / (size("") + size("t") - both), F.lit(0.0))
    best = j.groupBy("chart_id", "kind", "ordinal").agg(F.max(iou).alias("v"))
    return best.agg(F.count("*").alias("n"), F.round(F.avg("v"), 6).alias("value"))


@query
def cleaning_ablation(spark, d):
    """Accuracy with and without the saturation threshold under rising noise."""
    points = held(balanced_points(spark, d, "supplier", 1))
    true, rows = held(true_series(points, "wide")), []
    px = held(raster.ink(points, synth.coloured(points, "wide"), "line"))
    for noise in (0, 60, 15):
        images = raster.packed(raster.degraded(px, noise) if noise else px)
        pred = held(learned.predict_each(images, {"on": {"clean": True}, "off": {"clean": False}}))  # no image is kept
        rows += [scored(measure.series_no_ocr(pred.filter(F.col("variant") == v), true), "cleaning_ablation", f"noise_{noise}_{v}") for v in ("on", "off")]
    return union(rows)


@query
def saturation_sweep(spark, d):
    """Accuracy by saturation threshold."""
    points = balanced_points(spark, d, "supplier", 1)
    images, true = held(rendered(points, "wide", noise=30)), true_series(points, "wide")
    return union([scored(measure.series_no_ocr(learned.predict(images, threshold=t), true), "saturation_sweep", f"threshold_{t}") for t in (0, 32, 64, 128, 250)])


@query
def width_sweep(spark, d):
    """Accuracy by half-widths of the colour ranges."""
    points = balanced_points(spark, d, "supplier", 1)
    images, true = held(rendered(points, "wide")), true_series(points, "wide")
    return union([scored(measure.series_no_ocr(learned.predict(images, widths=w), true), "width_sweep", "_".join(map(str, w))) for w in ((2, 25, 40), (10, 10, 40), (10, 25, 40), (40, 25, 40), (90, 25, 40))])


@query
def embedding_colors(spark, d, k: int = 10):
    """One global colour space: MLlib k-means of embedding components as colours, and the purity of its clusters."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    from .queries import _embedding_colours

    px = _embedding_colours(spark, d).withColumn("w", F.lit(1.0))
    rows = VectorAssembler(inputCols=["r", "g", "b"], outputCol="features").transform(px)
    got = KMeans(k=k, seed=1, weightCol="w", maxIter=15).fit(rows).transform(rows).groupBy("prediction", "label").agg(F.count("*").alias("m"))
    top = got.groupBy("prediction").agg(F.max("m").alias("top"), F.sum("m").alias("all"))
    return scored(top.agg(F.sum("all").alias("n"), F.round(F.sum("top") / F.sum("all"), 6).alias("value")), "embedding_colors", "embeddings", "purity")


@query
def chance_level(spark, d):
    """Random guess and majority on raw and on balanced charts."""
    rows = []
    for corpus, points in (("raw", FAMILIES["customer_status"](spark, d)), ("balanced", balanced_points(spark, d, "customer_status", 6))):
        true = true_series(points)
        rows.append(scored(measure.series_no_ocr(baseline.random_guess(true.drop("relation")), true), "chance_level", f"{corpus}_guess"))
        rows.append(scored(measure.series_no_ocr(baseline.majority(true.drop("relation"), true), true), "chance_level", f"{corpus}_majority"))
    return union(rows)


@query
def training_size(spark, d):
    """Held-out and validation accuracy of the network by number of training charts, over two seeds."""
    points = held(steady(balanced_points(spark, d, "customer", 8)))
    test = charts_behind(points, 300)
    true, sizes = held(true_series(test)), {f"train_{n}_seed_{seed}": (n, seed) for n in (25, 100, 300) for seed in (0, 1)}
    models = {name: model_for(points, n, plot_type="line", epochs=15, seed=seed) for name, (n, seed) in sizes.items()}
    pred, rows = held(learned.predict_each(rendered(test), {name: {"model": m} for name, m in models.items()})), []
    for name, (n, _) in sizes.items():
        rows += [scored(measure.series_no_ocr(pred.filter(F.col("variant") == name), true), "training_size", name), validation(points, models[name], "training_size", name, n // 2)]
    return union(rows)


@query
def fine_tuning(spark, d):
    """A plain model on diverse charts before and after a short training on thirty of them."""
    diverse = held(training_points(spark, d, 4))
    model = plain_model(spark, d)
    tuned = model_for(diverse, 30, "wide", noise=60, epochs=8, seed=1, start=model, style="diverse")
    test = charts_behind(diverse, 30, 1)
    true = held(true_series(test, "wide"))
    pred = held(learned.predict_each(rendered(test, "wide", "mixed", 60, "diverse"), {"before": {"model": model}, "after": {"model": tuned}}))
    return union([scored(measure.series_no_ocr(pred.filter(F.col("variant") == name), true), "fine_tuning", name) for name in ("before", "after")])


@query
def learning_alone(spark, d):
    """A network trained to count relations on whole charts, against the full chain, by the counts of each chart."""
    points, train = balanced_points(spark, d, "supplier", 1), training_points(spark, d)
    use = first_charts(train, 300)
    counter = learned.train(learned.count_examples(rendered(use), true_series(use)), epochs=25, validate=True)
    images, true = held(rendered(points)), true_series(points)
    chain = scored(measure.raw(learned.predict(images, model_for(train, 100, plot_type="line", epochs=20)), true), "learning_alone", "full_chain")
    return union([chain, scored(measure.raw(learned.count_head(images, counter), true), "learning_alone", "network_only"), validation(use, counter, "learning_alone", "network_only", 150)])


@query
def detector_cost(spark, d):
    """The end-to-end measures with true facets, with the programmed detector and with the single-shot detector: what each costs."""
    points = held(balanced_points(spark, d, "supplier", 1))
    learn = max(1, min(40, points.select("chart_id").distinct().count() // 2))
    first = held(first_charts(points, learn))
    images, facets = text.annotated(rendered(first), synth.styles(first).select("chart_id", "title", "x_label", "y_label", *text.PLACES), true_series(first), held)
    ssd, test = trained_detector(images, facets), held(charts_behind(points, learn))
    return _end_to_end(test, None, "detector_cost", {name: name for name in ("truth", "layout", "ssd")}, ssd=ssd)


@query
def cost_profile(spark, d):
    """Compression of pixels to colours and distance evaluations of the k sweep, by family."""
    rows = []
    for family in ("supplier", "nation", "customer_status"):
        points = FAMILIES[family](spark, d)
        hist = cluster.histogram(cluster.saturate(raster.degraded(raster.ink(points, synth.coloured(points), "line"))), raster.W * raster.H)
        per = hist.groupBy("chart_id").agg(F.count("*").alias("h"))
        rows.append(scored(per.agg(F.count("*").alias("n"), F.round(F.lit(float(raster.W * raster.H)) / F.avg("h"), 6).alias("value")), "cost_profile", family, "pixels_per_colour"))
        rows.append(scored(per.agg(F.count("*").alias("n"), F.sum(F.col("h") * cluster.K_MAX * (cluster.K_MAX + 1) / 2).alias("value")), "cost_profile", family, "distances_per_round"))
    return union(rows)


def crafted(ys: np.ndarray, xs: np.ndarray) -> dict[str, tuple[np.ndarray, int]]:
    """Charts of one given line on which the method is known to fail or to need its special cases, and the number of series it finds."""
    from ..functions.color import np_full_hue

    hue = lambda h: np_full_hue(np.array([h]))[0]

    def blank(colour=(255, 255, 255)):
        return np.full((raster.H, raster.W, 3), colour, np.uint8)

    def line(img, colour, down=0, step=1):
        on = xs % step == 0
        img[np.minimum(ys[on] + down, raster.H - 1), xs[on]] = colour
        return img

    axes = blank()
    axes[raster.TOP + raster.IH + 2, 10:150] = axes[10 : raster.TOP + raster.IH, 10] = (0, 0, 255)
    two_tone = blank()
    two_tone[:, raster.W // 2 :] = (255, 255, 0)
    near = line(line(blank(), hue(60)), hue(66), 8)
    wrap = line(line(blank(), hue(178)), hue(2), 0, 2)
    return {
        "plain_line": (line(blank(), (255, 0, 0)), 1),
        "coloured_axes_become_a_series": (line(axes, (255, 0, 0)), 2),
        "gray_line_is_lost": (line(blank(), (90, 90, 90)), 0),
        "two_tone_background_becomes_a_series": (line(two_tone, (255, 0, 0)), 2),
        "dark_noise_survives": (line(blank(), (10, 0, 0)), 1),
        "near_hues_merge": (near, 1),
        "red_wraps_around": (wrap, 1),
        "blank": (blank(), 0),
    }


@query
def failure_catalog(spark, d):
    """chart_id, case, expected and found number of series, and the largest share of one mask that another one covers: every case on the line of finished orders of every nation."""
    import pyarrow as pa

    points = held(FAMILIES["nation"](spark, d).filter("series_key = 'F'"))
    lines = raster.line(points.withColumn("series_no", F.lit(1))).groupBy("chart_id").agg(F.sort_array(F.collect_list(F.struct("py", "px"))).alias("ink"))  # at most a canvas of pixels each

    def run(batches):
        for batch in batches:
            out = []
            for chart, ink in zip(batch.column("chart_id").to_pylist(), batch.column("ink").to_pylist()):
                for case, (img, want) in crafted(np.array([p["py"] for p in ink]), np.array([p["px"] for p in ink])).items():
                    _, found = cluster.np_series(img, "repeat")
                    shared = max((float((a & b).sum() / a.sum()) for i, (_, a) in enumerate(found) for j, (_, b) in enumerate(found) if i != j), default=0.0)
                    out.append({"chart_id": chart, "case": case, "expected": want, "found": len(found), "shared": round(shared, 6)})
            if out:
                yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("chart_id", pa.int64()), ("case", pa.string()), ("expected", pa.int32()), ("found", pa.int32()), ("shared", pa.float64())]))

    return lines.mapInArrow(run, "chart_id long, case string, expected int, found int, shared double")
