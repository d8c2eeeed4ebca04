"""Synthetic chart styles: every attribute fixed or drawn from the chart's id, the same in any run and engine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import draw, pick

TYPES = ("bar", "line", "scatter")
#: Colours of the training series (fixed values): red, green, blue; and a wider pool.
RGB3 = ((255, 0, 0), (0, 160, 0), (0, 0, 255))
WIDE = ((230, 25, 75), (60, 180, 75), (0, 130, 200), (245, 130, 48), (145, 30, 180), (0, 200, 200), (240, 50, 230), (150, 120, 20))
STYLES = ("plain", "grid", "dark", "wide_line", "dashed", "markers")


def random_label(key: Column, attr: str, lo: int = 3, hi: int = 12, seed: int = 0) -> Column:
    """lo to hi letters of either case, each from its own draw."""
    size = (draw(key, f"{attr}-size", seed) % (hi - lo + 1) + lo).cast("int")
    text = F.array_join(F.transform(F.sequence(F.lit(1), F.lit(hi)), lambda i: F.substring(F.lit("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"), (F.conv(F.substring(F.md5(F.concat_ws(":", key.cast("string"), F.lit(attr), i.cast("string"), F.lit(str(seed)))), 1, 8), 16, 10).cast("long") % 52).cast("int") + 1, 1)), "")
    return F.substring(text, F.lit(1), size)


def styles(charts: DataFrame, fixed: dict | None = None, pool: str = "default", seed: int = 0) -> DataFrame:
    """chart_id, plot_type, style, title, x_label, y_label and where title, labels and legend stand, for every chart id."""
    fixed, key = fixed or {}, F.col("chart_id")
    made = {
        "plot_type": pick(key, "type", list(TYPES), seed),
        "style": pick(key, "style", list(STYLES), seed) if pool == "diverse" else F.lit("plain"),
        "title": random_label(key, "title", 6, 12, seed),
        "x_label": random_label(key, "x_label", 3, 12, seed),
        "y_label": random_label(key, "y_label", 3, 12, seed),
        "title_x": (draw(key, "title_x", seed) % 60 + 20).cast("int"),
        "x_label_x": (draw(key, "x_label_x", seed) % 60 + 30).cast("int"),
        "y_label_y": (draw(key, "y_label_y", seed) % 40 + 14).cast("int"),
        "legend_y": (draw(key, "legend_y", seed) % 24 + 14).cast("int"),
    }
    return charts.select("chart_id").distinct().select("chart_id", *((F.lit(fixed[k]) if k in fixed else c).alias(k) for k, c in made.items()))


def coloured(series: DataFrame, palette: str = "rgb3") -> DataFrame:
    """series_no (order of the key in its chart), r, g, b for every series.

    Palettes ``rgb3`` and ``wide`` go by number, so colours of a chart differ; ``drawn`` draws each series' colour from the wide pool.
    """
    pool = RGB3 if palette == "rgb3" else WIDE
    rank = F.dense_rank().over(Window.partitionBy("chart_id").orderBy("series_key"))
    numbered = series.select("chart_id", "series_key").distinct().withColumn("series_no", rank.cast("int"))
    at = draw(F.concat_ws("|", "chart_id", "series_key"), "colour") if palette == "drawn" else F.col("series_no") - 1
    at = (at % len(pool)).cast("int") + 1
    return numbered.select("chart_id", "series_key", "series_no", *(F.element_at(F.array(*(F.lit(c[i]) for c in pool)), at).alias(n) for i, n in enumerate("rgb")))
