"""Registered queries and, where SQL can express them, their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.color import full_hue, with_hsv
from ..functions.draws import draw, pick
from ..operators import baseline, cluster, legend, measure, raster, synth, text, truth
from ..sources.families import FAMILIES, POINTS_SQL, trend
from ..sources.tables import page_titles, table
from . import sql as S

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Registers a function under its name, with its oracle."""
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _family(name: str) -> None:
    def run(spark: SparkSession, d: str) -> DataFrame:
        return truth.relations(FAMILIES[name](spark, d))

    run.__name__ = f"relation_class_{name}"
    query(truth.relations_sql(POINTS_SQL[name]))(run)


for _name in FAMILIES:
    _family(_name)


@query(S.RELATION_TUPLES)
def relation_tuples(spark, d):
    rel = truth.relations(FAMILIES["supplier"](spark, d))
    labels = table(spark, d, "supplier", "s_suppkey", "s_name").select(F.col("s_suppkey").alias("chart_id"), F.lit("ship year").alias("x_label"), F.concat(F.lit("revenue of "), "s_name").alias("y_label"))
    return legend.tuples(rel.withColumnRenamed("series_key", "series_label"), labels)


@query(S.SPEARMAN_PLAIN)
def spearman_without_ties(spark, d):
    got = truth.spearman(FAMILIES["customer_status"](spark, d), ties="none")
    return got.select("chart_id", "series_key", "n", F.round("rho", 6).alias("rho"))


@query(S.theta_counts())
def theta_registry(spark, d):
    got = truth.apply(FAMILIES["supplier"](spark, d), ("corr3", "slope", "kendall", "monotone"))
    return got.groupBy("theta", "label").agg(F.count("*").alias("n"))


@query(S.theta("slope"))
def theta_slope(spark, d):
    return truth.apply(FAMILIES["nation"](spark, d), ("slope",))


@query(S.theta("kendall"))
def theta_kendall(spark, d):
    return truth.apply(FAMILIES["nation"](spark, d), ("kendall",))


@query(S.theta("monotone"))
def theta_monotone(spark, d):
    return truth.apply(FAMILIES["nation"](spark, d), ("monotone",))


@query(S.theta("pearson"))
def theta_pearson(spark, d):
    return truth.apply(FAMILIES["nation"](spark, d), ("pearson",))


@query(S.STYLES_)
def style_assign(spark, d):
    return synth.styles(table(spark, d, "supplier").select(F.col("s_suppkey").alias("chart_id")), pool="diverse")


@query(S.COLOURS)
def series_colours(spark, d):
    return synth.coloured(FAMILIES["customer_status"](spark, d))


@query(S.TREND)
def trend_family(spark, d):
    got = trend(FAMILIES["supplier"](spark, d))
    return got.groupBy("chart_id", "series_key").agg(F.max("slope").alias("slope"), F.sum("y").cast("long").alias("total"), F.count("*").alias("n"))


def _ink(spark, d, plot_type, family="supplier", palette="rgb3"):
    points = FAMILIES[family](spark, d)
    return raster.ink(points, synth.coloured(points, palette), plot_type)


@query(S.ink("scatter"))
def raster_scatter(spark, d):
    return _ink(spark, d, "scatter")


@query(S.ink("line"))
def raster_line(spark, d):
    return _ink(spark, d, "line")


@query(S.ink("bar"))
def raster_bar(spark, d):
    return _ink(spark, d, "bar")


def _one_style(spark, d, style, plot_type="line"):
    """Ink of all supplier charts in one type and style."""
    points = FAMILIES["supplier"](spark, d)
    made = points.select("chart_id").distinct().select("chart_id", F.lit(plot_type).alias("plot_type"), F.lit(style).alias("style"))
    return raster.styled_ink(points, synth.coloured(points), made)


def _style(name: str) -> None:
    def run(spark, d):
        return _one_style(spark, d, name)

    run.__name__ = f"raster_style_{name}"
    query(S.styled("line", name))(run)


for _name in ("grid", "dark", "wide_line", "dashed", "markers"):
    _style(_name)


@query(S.mixed())
def raster_mixed(spark, d):
    """Every chart in the type and style that it draws: ink, its gray part and its places per chart."""
    points = FAMILIES["supplier"](spark, d)
    styles = synth.styles(points, pool="diverse")
    px = raster.styled_ink(points, synth.coloured(points), styles)
    got = px.groupBy("chart_id", "dark").agg(F.count("*").alias("ink"), F.sum(F.col("series_no").isNull().cast("long")).alias("gray"), F.sum("px").alias("sx"), F.sum("py").alias("sy"), F.count_distinct("r", "g", "b").alias("colours"))
    return got.join(styles.select("chart_id", "plot_type", "style"), "chart_id")


@query(S.OVERDRAWN)
def raster_overdraw(spark, d):
    """Per series: its line's pixels, and those that a series above it hides."""
    points = FAMILIES["supplier"](spark, d)
    numbered = points.join(synth.coloured(points).select("chart_id", "series_key", "series_no"), ["chart_id", "series_key"])
    per = raster.line(numbered).groupBy("chart_id", "px", "py").agg(F.collect_list("series_no").alias("of"), F.max("series_no").alias("top"))  # the series of one chart at most
    return per.select("chart_id", "top", F.explode("of").alias("series_no")).groupBy("chart_id", "series_no").agg(F.count("*").alias("drawn"), F.sum((F.col("top") > F.col("series_no")).cast("long")).alias("hidden"))


@query(S.LABELS)
def random_labels(spark, d):
    keys = FAMILIES["customer_status"](spark, d).select("chart_id", "series_key").distinct()
    return keys.select("chart_id", "series_key", _legend_label().alias("label"))


def _legend_label():
    return synth.random_label(F.concat_ws("|", "chart_id", "series_key"), "legend", 3, 9)


@query(S.FACETS)
def facet_truth_boxes(spark, d):
    """Boxes and texts of title, axis labels and legend where each chart's style places them, as drawn."""
    points = FAMILIES["supplier"](spark, d)
    series = synth.coloured(points).withColumn("series_label", _legend_label())
    return text.annotated(raster.packed(_ink(spark, d, "line")), synth.styles(points), series)[1]


@query(S.SPECKLE)
def noise_speckle(spark, d):
    return raster.degraded(_ink(spark, d, "scatter")).select("chart_id", "px", "py", "r", "g", "b")


@query(S.HSV_EMBEDDINGS)
def rgb_to_hsv(spark, d):
    return with_hsv(_embedding_colours(spark, d)).select("vec_id", "r", "g", "b", "h", "s", "v")


def _embedding_colours(spark, d):
    e = F.col("embedding")
    put = lambda i: F.greatest(F.lit(0), F.least(F.lit(255), F.floor((F.get(e, F.lit(i)).cast("double") + 0.5) * 255))).cast("int")
    return table(spark, d, "embeddings", "vec_id", "label", "embedding").select("vec_id", "label", put(0).alias("r"), put(1).alias("g"), put(2).alias("b"))


@query(S.saturated("white"))
def saturate_white(spark, d):
    return cluster.saturate(raster.degraded(_ink(spark, d, "scatter", palette="wide")), background="white").groupBy("chart_id", "r", "g", "b").agg(F.count("*").alias("n"))


@query(S.saturated("black"))
def saturate_black(spark, d):
    return cluster.saturate(raster.degraded(_ink(spark, d, "scatter", palette="wide")), background="black").groupBy("chart_id", "r", "g", "b").agg(F.count("*").alias("n"))


@query(S.HISTOGRAM)
def color_histogram(spark, d):
    return cluster.histogram(_ink(spark, d, "line"), raster.W * raster.H)


@query(S.DISTINCT)
def distinct_colors(spark, d):
    px = raster.degraded(_ink(spark, d, "scatter", palette="wide"))
    return px.groupBy("chart_id").agg(F.count_distinct("r", "g", "b").alias("colours"), F.count("*").alias("ink"))


@query(S.ranges())
def hsv_ranges(spark, d):
    return cluster.ranges(_range_colours(spark, d))


@query(S.ranges(literal=True))
def range_literal_ablation(spark, d):
    return cluster.ranges(_range_colours(spark, d), bounds="literal")


@query(S.WRAPPED)
def hsv_ranges_wrap(spark, d):
    """Ranges of the full hues of all vectors whose colour is about red, where hues wrap around."""
    h = with_hsv(_range_colours(spark, d)).filter("h < 15 or h > 165")
    return cluster.ranges(h.select("chart_id", "series_no", *(c.alias(n) for n, c in zip("rgb", full_hue(F.col("h"))))))


@query(S.ranges(s=10))
def range_narrow_saturation(spark, d):
    return cluster.ranges(_range_colours(spark, d), (10, 10, 40))


def _range_colours(spark, d):
    return _embedding_colours(spark, d).select(F.col("vec_id").alias("chart_id"), F.lit(1).alias("series_no"), "r", "g", "b")


@query(S.ASSIGN)
def kmeans_assign_given_centers(spark, d):
    px = _embedding_colours(spark, d)
    pts = px.groupBy("r", "g", "b").agg(F.count("*").alias("w")).withColumn("chart_id", F.lit(0).cast("long"))
    means = px.groupBy("label").agg(*(F.floor(F.avg(c)).cast("int").alias(c) for c in "rgb")).select(F.lit(0).cast("long").alias("chart_id"), F.col("label").alias("cid"), "r", "g", "b")
    return cluster.assign(pts, means).groupBy("cid").agg(F.sum("w").alias("n"), F.sum(F.col("w") * F.col("d2")).alias("sse"))


@query()
def k_select_rules(spark, d):
    """k by every rule, against the truth of series + 1, for each family with distinct colours."""
    out = None
    for family in ("supplier", "nation", "customer_status"):
        points = FAMILIES[family](spark, d)
        got = cluster.select_k(cluster.histogram(raster.ink(points, synth.coloured(points), "line"), raster.W * raster.H), ("corrected", "knee", "repeat"))
        # Colours that are seen, the background among them, are what a histogram of clean lines holds.
        row = got.agg(F.count("*").alias("charts"), *(F.round(F.avg((F.col(f"k_{r}") == F.col("colours")).cast("double")), 6).alias(r) for r in ("knee", "corrected", "repeat"))).withColumn("family", F.lit(family))
        out = row if out is None else out.unionByName(row)
    return out


@query(S.CLEAN_CENTERS)
def background_drop(spark, d):
    hist = cluster.histogram(cluster.saturate(_ink(spark, d, "line")), raster.W * raster.H)
    return cluster._foreground(cluster.exact_clusters(hist).select("chart_id", "cid", *(F.col(c).cast("double").alias(c) for c in "rgb"), "w"))


def _masks(spark, d, plot_type="line", family="supplier"):
    """Series found by colour and their masks. Colours are cleaned and measured once each per chart; pixels join the result by colour."""
    px = _ink(spark, d, plot_type, family).select("chart_id", "px", "py", "r", "g", "b")
    of = cluster.cleaned_colours(px)
    hist = cluster.histogram(of.select("chart_id", F.col("cr").alias("r"), F.col("cg").alias("g"), F.col("cb").alias("b"), "w"), raster.W * raster.H)
    found = cluster._foreground(cluster.exact_clusters(hist).select("chart_id", "cid", *(F.col(c).cast("double").alias(c) for c in "rgb"), "w"))
    return found, cluster.masks_by_colour(px, of, cluster.ranges(found))


@query(S.MASKS)
def masks_by_range(spark, d):
    _, m = _masks(spark, d)
    return m.groupBy("chart_id", "series_no").agg(F.count("*").alias("ink"), F.sum("px").alias("sx"), F.sum("py").alias("sy"))


@query(S.OVERLAP)
def mask_overlap(spark, d):
    """Share of pixels of each chart that several series' marks cover, from the marks before painting."""
    points = FAMILIES["supplier"](spark, d)
    numbered = points.join(synth.coloured(points).select("chart_id", "series_key", "series_no"), ["chart_id", "series_key"])
    per = raster.scatter(numbered).groupBy("chart_id", "px", "py").agg(F.count("*").alias("k"))
    return per.groupBy("chart_id").agg(F.count("*").alias("pixels"), F.sum((F.col("k") > 1).cast("long")).alias("shared"))


@query(S.PROGRAMMED)
def programmed_relations(spark, d):
    """Rank correlation of each mask's columns: the classifier without learning, from rendered pixels only."""
    found, m = _masks(spark, d)
    rel = truth.relations(cluster.column_points(m)).select("chart_id", F.col("series_key").cast("int").alias("series_no"), "relation")
    return found.select("chart_id", "series_no", "r", "g", "b").join(rel, ["chart_id", "series_no"])


def _predicted(spark, d):
    points = FAMILIES["supplier"](spark, d)
    true = truth.relations(points).join(synth.coloured(points), ["chart_id", "series_key"])
    return programmed_relations(spark, d), true, points


@query(S.score("no_ocr"))
def series_no_ocr(spark, d):
    pred, true, _ = _predicted(spark, d)
    return measure.series_no_ocr(pred, true)


@query(S.score("raw"))
def raw_score(spark, d):
    pred, true, _ = _predicted(spark, d)
    return measure.raw(pred, true)


@query(S.score("boundary"))
def boundary_excluded(spark, d):
    pred, true, points = _predicted(spark, d)
    rho = truth.spearman(points)
    return measure.series_no_ocr(pred, measure.without_boundary(true, rho, "series"))


@query(S.BOUNDARY)
def boundary_series(spark, d):
    return measure.boundary(truth.spearman(FAMILIES["customer_status"](spark, d))).select("chart_id", "series_key")


@query(S.score("strata"))
def strata_rollup(spark, d):
    """Colour-based accuracy by hardness (a series near the cut) and in total."""
    pred, true, points = _predicted(spark, d)
    hard = measure.boundary(truth.spearman(points)).select("chart_id").distinct().withColumn("hard", F.lit(1))
    per = measure.per_chart_no_ocr(pred, true).join(hard, "chart_id", "left").withColumn("hardness", F.when(F.col("hard").isNull(), "easy").otherwise("hard"))
    return measure.strata(per, "hardness").select(F.coalesce("hardness", F.lit("total")).alias("hardness"), "n", "value")


@query(S.score("confusion"))
def confusion_pivot(spark, d):
    pred, true, _ = _predicted(spark, d)
    return measure.confusion(_named(pred, true), true)


def _named(pred, true):
    """Predicted relations under the series' own keys, matched by hue."""
    t = with_hsv(true.select("chart_id", "series_key", "r", "g", "b")).select("chart_id", "series_key", "h")
    p = with_hsv(pred.select("chart_id", "relation", "r", "g", "b")).select("chart_id", "relation", F.col("h").alias("ph"))
    gap = F.abs(F.col("h") - F.col("ph"))
    return t.join(p, "chart_id").filter(F.least(gap, 180 - gap) <= 10).select("chart_id", "series_key", "relation")


@query(S.EDIT)
def edit_tolerance(spark, d):
    """Part names against their confused readings: share within two and within five edits."""
    n = table(spark, d, "part", "p_name").distinct().select("p_name", text.confuse(F.col("p_name"), 2).alias("seen"))
    # Lengths of names within reach differ by the limit at most: an equality join on length bands, however many names there are.
    seen = n.select("seen").distinct()
    band = lambda c: F.call_function("div", F.length(c).cast("long"), F.lit(6).cast("long"))
    left = n.select("p_name", F.explode(F.array(band("p_name") - 1, band("p_name"), band("p_name") + 1)).alias("band"))
    near = left.join(seen.withColumn("band", band("seen")), "band").agg(*(F.sum(measure.label_within(F.col("p_name"), F.col("seen"), k).cast("long")).alias(f"within_{k}") for k in (2, 5)))
    many = n.agg(F.count("*").alias("a"), F.count_distinct("seen").alias("b")).select((F.col("a") * F.col("b")).alias("n"))
    return many.join(near)  # one row each


@query(S.AXIS)
def axis_accuracy(spark, d):
    t = _axis_truth(spark, d)
    pred = t.select("chart_id", text.confuse(F.col("x_label"), 3, 1).alias("x_label"), text.confuse(F.col("y_label"), 3, 2).alias("y_label"))
    return measure.axis(pred, t, 0).unionByName(measure.axis(pred, t, 5)).unionByName(measure.axis(pred, t, 0, "label"))


def _axis_truth(spark, d):
    return synth.styles(table(spark, d, "supplier").select(F.col("s_suppkey").alias("chart_id"))).select("chart_id", "x_label", "y_label")


@query(S.legend_("median"))
def legend_median(spark, d):
    return _legend(spark, d, "median")


@query(S.legend_("nearest"))
def legend_nearest(spark, d):
    return _legend(spark, d, "nearest")


def _legend(spark, d, anchor):
    """Texts beside colour keys, in a box that wrongly holds data pixels as well."""
    points = FAMILIES["supplier"](spark, d)
    c = synth.coloured(points)
    texts = c.select("chart_id", F.col("series_no").alias("ordinal"), F.col("series_key").alias("text"), F.lit(140).alias("cx"), (20 + 11 * F.col("series_no")).alias("cy"))
    keys = c.select("chart_id", "series_no", F.explode(F.sequence(F.lit(124), F.lit(129))).alias("px"), (20 + 11 * F.col("series_no")).alias("y")).select("chart_id", "series_no", "px", F.explode(F.array(F.col("y") - 1, F.col("y"), F.col("y") + 1)).alias("py"))
    stray = raster.ink(points, c, "scatter").filter("px > 132 and py between 24 and 60").select("chart_id", "series_no", "px", "py")
    return legend.assign(texts, keys.unionByName(stray), anchor)


@query(S.TURNS)
def turning_points(spark, d):
    return baseline.turning_points(baseline.column_trace(_ink(spark, d, "line")))


@query(S.INTERPOLATED)
def interpolate_asof(spark, d):
    t = baseline.turning_points(baseline.column_trace(_ink(spark, d, "line")))
    return baseline.interpolated(t)


@query(S.EXTRACTOR)
def baseline_relation(spark, d):
    got = baseline.interpolated(baseline.turning_points(baseline.column_trace(_ink(spark, d, "line"))))
    return truth.relations(got).select("chart_id", "relation")


@query(S.GUESS)
def random_guess(spark, d):
    rel = truth.relations(FAMILIES["customer_status"](spark, d))
    return baseline.random_guess(rel.select("chart_id", "series_key")).groupBy("relation").agg(F.count("*").alias("n"))


@query(S.MAJORITY)
def majority_guess(spark, d):
    rel = truth.relations(FAMILIES["customer_status"](spark, d))
    guess = baseline.majority(rel.select("chart_id", "series_key"), rel)
    return measure.balanced(guess, rel)


@query(S.FILTERED)
def corpus_filter(spark, d):
    """Line charts of up to three series, each at least 60 % of the chart's height tall, of colours farther apart than the ranges are wide."""
    return eligible(FAMILIES["supplier"](spark, d))


def eligible(points: DataFrame, most: int = 3, tenths: int = 6, palette: str = "drawn") -> DataFrame:
    """chart_id of charts that pass the corpus filter: type, number and height of series, distance of their colours."""
    per = points.groupBy("chart_id", "series_key").agg(F.min("y").alias("lo"), F.max("y").alias("hi"))
    chart = per.groupBy("chart_id").agg(F.count("*").alias("k"), F.min(F.col("hi") - F.col("lo")).alias("least"), (F.max("hi") - F.min("lo")).alias("span"))
    lines = pick(F.col("chart_id"), "type", list(synth.TYPES)) == "line"  # plain and dotted lines are one type in several styles
    tall = chart.filter(lines & (F.col("k") <= most) & (F.col("span") > 0) & (10 * F.col("least") >= tenths * F.col("span"))).select("chart_id")
    c = with_hsv(synth.coloured(points.join(tall, "chart_id", "left_semi"), palette)).select("chart_id", "series_no", "h", "s", "v")
    o = c.toDF("chart_id", "no", "h2", "s2", "v2")  # ``most`` series of a chart at most meet
    gap = F.abs(F.col("h") - F.col("h2"))
    dh, ds, dv = cluster.WIDTHS
    near = (F.least(gap, 180 - gap) <= dh) & (F.abs(F.col("s") - F.col("s2")) <= ds) & (F.abs(F.col("v") - F.col("v2")) <= dv)
    close = c.join(o, "chart_id").filter((F.col("series_no") < F.col("no")) & near).select("chart_id")
    return tall.join(close, "chart_id", "left_anti")


@query(S.SPLIT)
def train_test_split(spark, d):
    """First hundred of the filtered corpus for transfer; 101-200 and 201-300 for the control."""
    e = eligible(FAMILIES["customer_status"](spark, d))
    first = e.orderBy("chart_id").limit(300)  # numbered only after the cut: 300 rows
    return first.withColumn("n", F.row_number().over(Window.orderBy("chart_id"))).select("chart_id", F.when(F.col("n") <= 100, "transfer_test").when(F.col("n") <= 200, "control_train").otherwise("control_test").alias("role"))


@query(S.DISJOINT)
def train_test_disjoint(spark, d):
    """Sizes of the split's parts and the number of charts in more than one."""
    return train_test_split(spark, d).agg(
        F.count("*").alias("n"), F.count_distinct("chart_id").alias("charts"), (F.count("*") - F.count_distinct("chart_id")).alias("shared"),
        *(F.sum((F.col("role") == r).cast("long")).alias(r) for r in ("transfer_test", "control_train", "control_test")))


@query(S.HARDNESS)
def hardness_label(spark, d):
    """Why a chart is hard: more than three series, a series near the cut, or over 30 % of its ink shared."""
    points = FAMILIES["user"](spark, d)
    near = measure.boundary(truth.spearman(points)).groupBy("chart_id").agg(F.count("*").alias("near"))
    many = points.groupBy("chart_id").agg(F.count_distinct("series_key").alias("series"))
    numbered = points.join(synth.coloured(points, "wide").select("chart_id", "series_key", "series_no"), ["chart_id", "series_key"])
    per = raster.line(numbered).groupBy("chart_id", "px", "py").agg(F.count("*").alias("k")).groupBy("chart_id").agg(F.count("*").alias("pixels"), F.sum((F.col("k") > 1).cast("long")).alias("twice"))
    hard = (F.col("series") > 3) | F.col("near").isNotNull() | (10 * F.col("twice") > 3 * F.col("pixels"))
    return many.join(near, "chart_id", "left").join(per, "chart_id").select("chart_id", "series", F.coalesce("near", F.lit(0)).alias("near"), F.round(F.col("twice") / F.col("pixels"), 6).alias("shared"), hard.alias("hard"))


def _labelled(spark, d):
    """Programmed relations under the legend labels that a confusing reader sees, and the truth with its labels."""
    pred, true, _ = _predicted(spark, d)
    true = true.withColumn("series_label", _legend_label())
    seen = true.select("chart_id", "series_key", "series_no", text.confuse(F.col("series_label"), 2).alias("series_label"))
    return _named(pred, true).join(seen, ["chart_id", "series_key"]).select("chart_id", "series_no", "series_label", "relation"), true


@query(S.SERIES_ACCURACY)
def series_accuracy(spark, d):
    """Share of a chart's series whose label is read within two edits and whose relation is right."""
    return measure.series(*_labelled(spark, d))


@query(S.TOTAL_ACCURACY)
def total_accuracy(spark, d):
    """Mean of axis and series accuracy."""
    t = _axis_truth(spark, d)
    pred = t.select("chart_id", text.confuse(F.col("x_label"), 3, 1).alias("x_label"), text.confuse(F.col("y_label"), 3, 2).alias("y_label"))
    return measure.total(measure.axis(pred, t, 5), measure.series(*_labelled(spark, d)))


@query(S.DELTA)
def accuracy_delta(spark, d):
    """What leaving out series near the cut adds to the colour-based accuracy."""
    pred, true, points = _predicted(spark, d)
    clear = measure.without_boundary(true, truth.spearman(points), "series")
    return measure.delta(measure.series_no_ocr(pred, true), measure.series_no_ocr(pred, clear))


@query(S.CAUSES)
def failure_causes(spark, d):
    """Why axis labels fail: a facet not found, the other facet's text, a misreading; some of each are planted."""
    t = _axis_truth(spark, d)
    miss = lambda own, other: F.when(F.col("chart_id") % 7 == 0, "").when(F.col("chart_id") % 11 == 0, F.col(other)).otherwise(own)
    pred = t.select("chart_id", miss(text.confuse(F.col("x_label"), 3, 1), "y_label").alias("x_label"), miss(text.confuse(F.col("y_label"), 3, 2), "x_label").alias("y_label"))
    return measure.axis_causes(pred, t)


@query(S.MASK_QUALITY)
def mask_quality(spark, d):
    """Precision and recall of every series' mask against the ink that the renderer left visible."""
    found, m = _masks(spark, d)
    points = FAMILIES["supplier"](spark, d)
    return measure.masks(m, found, _ink(spark, d, "line"), synth.coloured(points))


@query(S.legend_accuracy())
def legend_accuracy(spark, d):
    """Share of legend texts that come to their own series, by anchor."""
    rows = [_legend(spark, d, a).agg(F.count("*").alias("n"), F.round(F.avg((F.col("ordinal") == F.col("series_no")).cast("double")), 6).alias("value")).withColumn("anchor", F.lit(a)) for a in ("median", "nearest")]
    return rows[0].unionByName(rows[1])


@query(S.text_only())
def text_only_baseline(spark, d):
    """Relations guessed from the legend's text alone: the commonest one of training series whose label begins alike."""
    rel = truth.relations(FAMILIES["customer_status"](spark, d)).filter("relation <> 'undefined'")
    rel = rel.select("chart_id", "series_key", "relation", F.lower(F.substring(_legend_label(), 1, 1)).alias("token"), (draw(F.col("chart_id"), "half") % 2).alias("half"))
    test = rel.filter("half = 1")
    return baseline.text_only(rel.filter("half = 0"), test).agg(F.count("*").alias("n"), F.round(F.avg((F.col("relation") == F.col("guess")).cast("double")), 6).alias("value"))


@query(S.PROPS)
def json_props(spark, d):
    e = table(spark, d, "events", "event_type", "props").select("event_type", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return e.groupBy("event_type").agg(F.count("k").alias("n"), F.sum("k").alias("total"))


@query(S.TITLES)
def titles_from_pages(spark, d):
    return page_titles(spark, d)


@query(S.SESSIONS)
def session_relations(spark, d):
    """Sessions of each user (a gap of half an hour ends one) and their numbers of points."""
    e = table(spark, d, "events", "user_id", "ts").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    s = e.groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return s.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


@query(S.WINDOWED)
def daily_relations(spark, d):
    """Relation of value over time per day and event type: tumbling windows as series."""
    p = FAMILIES["user"](spark, d)
    by_day = p.select(F.call_function("div", F.col("x"), F.lit(86_400_000_000)).alias("chart_id"), "series_key", "x", "y")
    return truth.relations(by_day)


@query(S.SETS)
def corpora_sets(spark, d):
    """Charts in both corpora, only in one, in either: the leakage check of a split."""
    a = eligible(FAMILIES["customer_status"](spark, d))
    b = FAMILIES["customer"](spark, d).groupBy("chart_id").agg(F.count("*").alias("k")).filter("k >= 8").select("chart_id")
    pieces = {"both": a.intersect(b), "first_only": a.exceptAll(b), "either": a.union(b).distinct()}
    out = None
    for name, df in pieces.items():
        row = df.agg(F.count("*").alias("n"), F.coalesce(F.sum("chart_id"), F.lit(0)).alias("total")).select(F.lit(name).alias("part"), "n", "total")
        out = row if out is None else out.unionByName(row)
    return out
