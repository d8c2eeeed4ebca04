"""Accuracy measures over predicted and true series; a chart without prediction scores nothing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.color import with_hsv
from .truth import against


def label_within(a: Column, b: Column, limit: int) -> Column:
    """Edit distance at most ``limit``; the bounded form stops early."""
    return F.coalesce(F.levenshtein(a, b, limit) >= 0, F.lit(False))


def axis(pred: DataFrame, truth: DataFrame, max_edit: int = 5, unit: str = "chart") -> DataFrame:
    """metric, n, value: charts whose two axis labels are right (``unit="label"``: labels); frames: chart_id, x_label, y_label."""
    p = pred.select("chart_id", F.col("x_label").alias("px"), F.col("y_label").alias("py")).dropDuplicates(["chart_id"])
    j = truth.select("chart_id", "x_label", "y_label").join(p, "chart_id", "left")
    x, y = label_within(F.col("px"), F.col("x_label"), max_edit), label_within(F.col("py"), F.col("y_label"), max_edit)
    hit = (x & y).cast("double") if unit == "chart" else (x.cast("double") + y.cast("double")) / 2
    return j.agg(F.count("*").alias("n"), F.round(F.avg(hit), 6).alias("value")).select(F.lit("axis").alias("metric"), "n", "value")


def _per_chart(truth: DataFrame, right: DataFrame) -> DataFrame:
    """chart_id, share of its defined true series that are right; right: chart_id, series_key."""
    t = truth.filter("relation <> 'undefined'").select("chart_id", "series_key")
    hit = right.select("chart_id", "series_key").distinct().withColumn("ok", F.lit(1.0))
    return t.join(hit, ["chart_id", "series_key"], "left").groupBy("chart_id").agg(F.avg(F.coalesce("ok", F.lit(0.0))).alias("share"))


def _mean(per: DataFrame, metric: str) -> DataFrame:
    return per.agg(F.count("*").alias("n"), F.round(F.avg("share"), 6).alias("value")).select(F.lit(metric).alias("metric"), "n", "value")


def series_right(pred: DataFrame, truth: DataFrame, max_edit: int = 2) -> DataFrame:
    """True series whose legend label is found within ``max_edit`` and whose relation agrees; each prediction used once per best match."""
    j = truth.select("chart_id", "series_key", "series_label", "relation").join(pred.select("chart_id", F.col("series_no").alias("no"), F.col("series_label").alias("pl"), F.col("relation").alias("pr")), "chart_id")
    j = j.withColumn("d", F.levenshtein("pl", "series_label", max_edit)).filter("d >= 0")
    by = lambda *k: F.row_number().over(Window.partitionBy(*k).orderBy("d", "no", "series_key"))
    best = j.withColumn("a", by("chart_id", "series_key")).filter("a = 1").withColumn("b", by("chart_id", "no")).filter("b = 1")
    return best.filter("pr = relation").select("chart_id", "series_key")


def series(pred: DataFrame, truth: DataFrame, max_edit: int = 2) -> DataFrame:
    return _mean(_per_chart(truth, series_right(pred, truth, max_edit)), "series")


def colour_right(pred: DataFrame, truth: DataFrame, widths: tuple[int, int, int] = (10, 25, 40), cleaned: bool = True) -> DataFrame:
    """True series whose colour lies in the range of a predicted series with the right relation (hue on its ring).

    Cleaning sets saturation and value of all ink to the full, so on ``cleaned`` charts the hue alone is compared.
    """
    t = with_hsv(truth.select("chart_id", "series_key", "relation", "r", "g", "b"))
    p = with_hsv(pred.select("chart_id", "series_no", F.col("relation").alias("pr"), "r", "g", "b")).select("chart_id", "series_no", "pr", *(F.col(c).alias(f"p{c}") for c in "hsv"))
    gap = F.abs(F.col("h") - F.col("ph"))
    near = F.least(gap, 180 - gap) <= widths[0]
    if not cleaned:
        near = near & (F.abs(F.col("s") - F.col("ps")) <= widths[1]) & (F.abs(F.col("v") - F.col("pv")) <= widths[2])
    return t.join(p, "chart_id").filter(near & (F.col("pr") == F.col("relation"))).select("chart_id", "series_key").distinct()


def series_no_ocr(pred: DataFrame, truth: DataFrame, widths: tuple[int, int, int] = (10, 25, 40)) -> DataFrame:
    return _mean(_per_chart(truth, colour_right(pred, truth, widths)), "series_no_ocr")


def per_chart_no_ocr(pred: DataFrame, truth: DataFrame, widths: tuple[int, int, int] = (10, 25, 40)) -> DataFrame:
    return _per_chart(truth, colour_right(pred, truth, widths))


def total(axis_row: DataFrame, series_row: DataFrame) -> DataFrame:
    """Mean of the two."""
    both = axis_row.select("n", "value").unionByName(series_row.select("n", "value"))
    return both.agg(F.max("n").alias("n"), F.round(F.avg("value"), 6).alias("value")).select(F.lit("total").alias("metric"), "n", "value")


def relation_counts(df: DataFrame) -> DataFrame:
    """chart_id, numbers of increasing, decreasing and neutral series."""
    return df.groupBy("chart_id").agg(*(F.sum((F.col("relation") == r).cast("long")).alias(r) for r in ("increasing", "decreasing", "neutral")))


def raw(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of charts whose three counts all agree."""
    p = relation_counts(pred).toDF("chart_id", "pi", "pd", "pn")
    j = relation_counts(truth).join(p, "chart_id", "left")
    ok = (F.coalesce("pi", F.lit(0)) == F.col("increasing")) & (F.coalesce("pd", F.lit(0)) == F.col("decreasing")) & (F.coalesce("pn", F.lit(0)) == F.col("neutral"))
    return j.agg(F.count("*").alias("n"), F.round(F.avg(ok.cast("double")), 6).alias("value")).select(F.lit("raw").alias("metric"), "n", "value")


def boundary(rho: DataFrame, low: tuple[int, int] = (1, 4), high: tuple[int, int] = (11, 20)) -> DataFrame:
    """Series with low <= |rho| <= high (the cut 0.4 give or take 0.15), by exact ratios; rho: output of ``truth.spearman``."""
    sums = F.col("xy"), F.col("xx"), F.col("yy")
    return rho.filter((F.col("xx") > 0) & (F.col("yy") > 0) & (against(*sums, low) >= 0) & (against(*sums, high) <= 0))


def without_boundary(df: DataFrame, rho: DataFrame, unit: str = "chart") -> DataFrame:
    """``df`` less charts (or series) that hold a series near the cut."""
    keys = ["chart_id"] if unit == "chart" else ["chart_id", "series_key"]
    return df.join(boundary(rho).select(*keys).distinct(), keys, "left_anti")


def confusion(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """relation (true), counts of predicted relations; frames: chart_id, series_key, relation."""
    j = truth.select("chart_id", "series_key", "relation").join(pred.select("chart_id", "series_key", F.col("relation").alias("p")), ["chart_id", "series_key"])
    return j.groupBy("relation").agg(*(F.sum((F.col("p") == r).cast("long")).alias(f"as_{r}") for r in ("increasing", "decreasing", "neutral")))


def strata(per_chart: DataFrame, *dims: str) -> DataFrame:
    """Mean share by every combination of the dimensions and their totals."""
    return per_chart.rollup(*dims).agg(F.count("*").alias("n"), F.round(F.avg("share"), 6).alias("value"), F.grouping_id().alias("level"))


def balanced(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """Mean over true relations of the share predicted right, beside the plain share and the majority's."""
    j = truth.filter("relation <> 'undefined'").select("chart_id", "series_key", "relation").join(pred.select("chart_id", "series_key", F.col("relation").alias("p")), ["chart_id", "series_key"], "left")
    per = j.groupBy("relation").agg(F.count("*").alias("n"), F.avg((F.coalesce(F.col("p") == F.col("relation"), F.lit(False))).cast("double")).alias("r"))
    return per.agg(F.sum("n").alias("n"), F.round(F.avg("r"), 6).alias("balanced"), F.round(F.sum(F.col("r") * F.col("n")) / F.sum("n"), 6).alias("plain"), F.round(F.max("n") / F.sum("n"), 6).alias("majority"))


def delta(a: DataFrame, b: DataFrame) -> DataFrame:
    """metric, difference of two runs' values."""
    return a.select("metric", F.col("value").alias("a")).join(b.select("metric", F.col("value").alias("b")), "metric").select("metric", "a", "b", F.round(F.col("b") - F.col("a"), 6).alias("delta"))


def axis_causes(pred: DataFrame, truth: DataFrame, max_edit: int = 5) -> DataFrame:
    """axis, cause, n: how every axis label came out; frames: chart_id, x_label, y_label, an empty text where no facet was found."""
    p = pred.select("chart_id", F.col("x_label").alias("px"), F.col("y_label").alias("py")).dropDuplicates(["chart_id"])
    j = truth.select("chart_id", "x_label", "y_label").join(p, "chart_id", "left").fillna("", ["px", "py"])
    row = lambda a, own, seen, other: F.struct(F.lit(a).alias("axis"), F.col(own).alias("label"), F.col(seen).alias("found"), F.col(other).alias("other"))
    each = j.select(F.inline(F.array(row("x", "x_label", "px", "y_label"), row("y", "y_label", "py", "x_label"))))
    near, swapped = label_within(F.col("found"), F.col("label"), max_edit), label_within(F.col("found"), F.col("other"), max_edit)
    cause = F.when(F.col("found") == "", "facet_missed").when(F.col("found") == F.col("label"), "exact").when(swapped & ~near, "facets_swapped").when(near, "misread_within_limit").otherwise("misread")
    return each.groupBy("axis", cause.alias("cause")).agg(F.count("*").alias("n"))


def masks(found: DataFrame, centres: DataFrame, ink: DataFrame, colours: DataFrame, hue: int = 10) -> DataFrame:
    """chart_id, series_no (true), precision, recall of the found masks whose colour is the series' colour."""
    p = with_hsv(centres.select("chart_id", "series_no", "r", "g", "b")).select("chart_id", F.col("series_no").alias("found"), F.col("h").alias("ph"))
    t = with_hsv(colours.select("chart_id", "series_no", "r", "g", "b")).select("chart_id", "series_no", "h")
    gap = F.abs(F.col("h") - F.col("ph"))
    own = t.join(p, "chart_id").filter(F.least(gap, 180 - gap) <= hue).select("chart_id", "series_no", "found")
    got = own.join(found.withColumnRenamed("series_no", "found"), ["chart_id", "found"]).select("chart_id", "series_no", "px", "py", F.lit(1).alias("m"), F.lit(0).alias("t"))
    both = got.unionByName(ink.select("chart_id", "series_no", "px", "py", F.lit(0).alias("m"), F.lit(1).alias("t"))).groupBy("chart_id", "series_no", "px", "py").agg(F.sum("m").alias("m"), F.max("t").alias("t"))
    s = both.groupBy("chart_id", "series_no").agg(F.sum(F.col("m") * F.col("t")).alias("hit"), F.sum("m").alias("got"), F.sum("t").alias("want")).filter("want > 0")
    return s.select("chart_id", "series_no", F.round(F.when(F.col("got") > 0, F.col("hit") / F.col("got")), 6).alias("precision"), F.round(F.col("hit") / F.col("want"), 6).alias("recall"))
