"""Legend text to series by pixels of the series' colour, and the join to relations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def in_box(px: DataFrame, boxes: DataFrame) -> DataFrame:
    """Pixels inside a chart's legend box; boxes: chart_id, x0, y0, x1, y1."""
    return px.join(boxes, "chart_id").filter(F.col("px").between(F.col("x0"), F.col("x1")) & F.col("py").between(F.col("y0"), F.col("y1"))).select(*px.columns)


def assign(texts: DataFrame, marks: DataFrame, anchor: str = "median", unique: bool = False) -> DataFrame:
    """chart_id, ordinal, text, series_no, d2: for each text (cx, cy) the series with the nearest mark or median mark.

    marks: chart_id, series_no, px, py of the legend box. ``unique`` keeps, per series, only its nearest text.
    """
    if anchor == "median":
        marks = marks.groupBy("chart_id", "series_no").agg(F.expr("percentile(px, 0.5)").alias("px"), F.expr("percentile(py, 0.5)").alias("py"))
    d2 = (F.col("cx") - F.col("px")) ** 2 + (F.col("cy") - F.col("py")) ** 2
    near = texts.join(marks, "chart_id").groupBy("chart_id", "ordinal", "text").agg(F.min(F.struct(d2.cast("double").alias("d2"), "series_no")).alias("m")).select("chart_id", "ordinal", "text", F.col("m.series_no").alias("series_no"), F.col("m.d2").alias("d2"))
    if unique:
        w = Window.partitionBy("chart_id", "series_no").orderBy("d2", "ordinal")
        near = near.withColumn("_n", F.row_number().over(w)).filter("_n = 1").drop("_n")
    return near


def join_relations(legend: DataFrame, relations: DataFrame) -> DataFrame:
    """chart_id, series_label, relation: text to colour joined with colour to relation; texts without a series stay."""
    return legend.select("chart_id", F.col("text").alias("series_label"), "series_no").join(relations.select("chart_id", "series_no", "relation"), ["chart_id", "series_no"], "left").select("chart_id", "series_no", "series_label", "relation")


def tuples(relations: DataFrame, labels: DataFrame) -> DataFrame:
    """chart_id, x_label, y_label, series_label, relation."""
    return relations.join(labels.select("chart_id", "x_label", "y_label"), "chart_id", "left").select("chart_id", "x_label", "y_label", "series_label", "relation")


def document(relations: DataFrame, labels: DataFrame) -> DataFrame:
    """One nested document per chart: title, axis labels, series sorted by label."""
    got = relations.groupBy("chart_id").agg(F.array_sort(F.collect_list(F.struct("series_label", "relation"))).alias("series"))
    return labels.select("chart_id", "title", "x_label", "y_label").join(got, "chart_id", "left")
