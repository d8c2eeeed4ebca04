"""Rendering points to ink: sparse pixel rows for the relational form, packed arrays for images.

The plot box lies inside a small canvas; x and y map to it by integer division, row 0 on top. Where marks overlap, the
series with the higher number lies on top.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import draw

W, H = 160, 120
LEFT, TOP, IW, IH = 20, 14, 120, 90


def _quot(a: Column, times: int, by: Column) -> Column:
    """a * times div by in whole numbers; a difference of microseconds times a box width stays far below 2^63."""
    return F.call_function("div", (a * times).cast("long"), by.cast("long"))


def placed(points: DataFrame) -> DataFrame:
    """points with px, py: their places in the plot box; a chart without extent is centred."""
    w = Window.partitionBy("chart_id")
    lo = points.select("*", F.min("x").over(w).alias("x0"), F.max("x").over(w).alias("x1"), F.min("y").over(w).alias("y0"), F.max("y").over(w).alias("y1"))
    px = F.when(F.col("x1") == F.col("x0"), LEFT + IW // 2).otherwise(LEFT + _quot((F.col("x") - F.col("x0")), IW - 1, F.col("x1") - F.col("x0")))
    py = F.when(F.col("y1") == F.col("y0"), TOP + IH // 2).otherwise(TOP + IH - 1 - _quot((F.col("y") - F.col("y0")), IH - 1, F.col("y1") - F.col("y0")))
    return lo.select(*points.columns, px.cast("int").alias("px"), py.cast("int").alias("py"))


def scatter(points: DataFrame, size: int = 3) -> DataFrame:
    """chart_id, series_no, px, py: squares about the points."""
    off = F.array(*(F.lit(k) for k in range(-(size // 2), size // 2 + 1)))
    p = placed(points).select("chart_id", "series_no", "px", "py").distinct()
    return p.withColumn("dx", F.explode(off)).withColumn("dy", F.explode(off)).select("chart_id", "series_no", (F.col("px") + F.col("dx")).alias("px"), (F.col("py") + F.col("dy")).alias("py")).distinct()


def line(points: DataFrame) -> DataFrame:
    """Segments between neighbours in the order of x: every column, with the gap to the next column filled."""
    w = Window.partitionBy("chart_id", "series_no").orderBy("x", "y")
    p = placed(points).select("chart_id", "series_no", "x", "y", "px", "py")
    p = p.select("chart_id", "series_no", "px", "py", F.lead("px").over(w).alias("qx"), F.lead("py").over(w).alias("qy"))
    p = p.withColumn("qx", F.coalesce("qx", "px")).withColumn("qy", F.coalesce("qy", "py"))
    c = p.withColumn("cx", F.explode(F.sequence("px", "qx")))
    run = F.col("qx") - F.col("px")

    def at(k: Column) -> Column:  # height of the segment k columns on; steps toward zero, as integer division does
        return F.when(run == 0, F.col("qy")).otherwise(F.col("py") + F.call_function("div", ((F.col("qy") - F.col("py")) * k).cast("long"), F.when(run == 0, 1).otherwise(run).cast("long")))

    k = F.col("cx") - F.col("px")
    here = F.when(run == 0, F.col("py")).otherwise(at(k))
    there = F.when(run == 0, F.col("qy")).otherwise(at(F.least(k + 1, run)))
    return c.withColumn("from", here.cast("int")).withColumn("to", there.cast("int")).select("chart_id", "series_no", F.col("cx").alias("px"), F.explode(F.sequence("from", "to")).alias("py")).distinct()


def bar(points: DataFrame) -> DataFrame:
    """One slot per x of the chart, a sub-slot per series, from the bottom of the box to the value."""
    w = Window.partitionBy("chart_id")
    p = placed(points).withColumn("slot", F.dense_rank().over(w.orderBy("x")) - 1).withColumn("slots", F.size(F.collect_set("x").over(w))).withColumn("many", F.max("series_no").over(w))
    wide = F.greatest(F.lit(1), F.call_function("div", F.lit(IW).cast("long"), (F.col("slots") * F.col("many")).cast("long"))).cast("int")
    p = p.withColumn("wide", wide).withColumn("at", (LEFT + F.call_function("div", F.col("slot").cast("long") * IW, F.col("slots").cast("long")) + (F.col("series_no") - 1) * F.col("wide")).cast("int"))
    p = p.groupBy("chart_id", "series_no", "at", "wide").agg(F.min("py").alias("py"))
    cols = F.sequence(F.col("at"), F.col("at") + F.greatest(F.lit(0), F.col("wide") - 2))
    return p.select("chart_id", "series_no", F.explode(cols).alias("px"), "py").select("chart_id", "series_no", "px", F.explode(F.sequence(F.col("py"), F.lit(TOP + IH - 1))).alias("py")).distinct()


MARKS = {"scatter": scatter, "line": line, "bar": bar}


def painted(marks: DataFrame, colours: DataFrame) -> DataFrame:
    """chart_id, px, py, series_no, r, g, b: the topmost mark of every pixel."""
    top = marks.groupBy("chart_id", "px", "py").agg(F.max("series_no").alias("series_no"))
    return top.join(colours.select("chart_id", "series_no", "r", "g", "b"), ["chart_id", "series_no"]).select("chart_id", "px", "py", "series_no", "r", "g", "b")


def ink(points: DataFrame, colours: DataFrame, plot_type: str = "line") -> DataFrame:
    """Ink pixels of charts of one type; points: chart_id, series_key, x, y."""
    numbered = points.join(colours.select("chart_id", "series_key", "series_no"), ["chart_id", "series_key"])
    return painted(MARKS[plot_type](numbered), colours)


#: Gray of grid lines, their distance, and the columns of a dash and of the gap behind it.
GRID, EVERY, DASH = 200, 15, 4


def styled_marks(marks: DataFrame, dots: DataFrame | None = None) -> DataFrame:
    """Marks (with a column ``style``) as their chart's style has them; ``dots`` are the squares of charts with markers."""
    off = lambda c: F.explode(F.when(F.col("style") == "wide_line", F.array(*map(F.lit, (-1, 0, 1)))).otherwise(F.array(F.lit(0)))).alias(c)
    out = marks.filter((F.col("style") != "dashed") | (F.col("px") % (2 * DASH) < DASH))
    out = out.select("*", off("dx")).select("*", off("dy")).select("chart_id", "series_no", (F.col("px") + F.col("dx")).alias("px"), (F.col("py") + F.col("dy")).alias("py"))
    return (out.unionByName(dots.filter("style = 'markers'").select("chart_id", "series_no", "px", "py")) if dots is not None else out).distinct()


def grid(charts: DataFrame) -> DataFrame:
    """Gray lines across the plot box of every chart: chart_id, px, py."""
    x, y = F.sequence(F.lit(LEFT), F.lit(LEFT + IW - 1)), F.sequence(F.lit(TOP), F.lit(TOP + IH - 1))
    cells = charts.select("chart_id", F.explode(x).alias("px")).select("chart_id", "px", F.explode(y).alias("py"))
    return cells.filter(((F.col("px") - LEFT) % EVERY == 0) | ((F.col("py") - TOP) % EVERY == 0))


def styled_ink(points: DataFrame, colours: DataFrame, styles: DataFrame) -> DataFrame:
    """Ink of charts of all types and styles: chart_id, px, py, series_no (null on grid lines), r, g, b, dark.

    styles: chart_id, plot_type, style. Dashes and markers are for lines, wide strokes for lines and scatters, grid and dark background for all.
    """
    numbered = points.join(colours.select("chart_id", "series_key", "series_no"), ["chart_id", "series_key"])
    of = styles.select("chart_id", "plot_type", "style")
    parts = []
    for kind, make in MARKS.items():
        mine = of.filter(F.col("plot_type") == kind).select("chart_id", "style")
        marks = make(numbered.join(mine.select("chart_id"), "chart_id", "left_semi")).join(mine, "chart_id")
        if kind == "line":
            dots = scatter(numbered.join(mine.filter("style = 'markers'").select("chart_id"), "chart_id", "left_semi")).join(mine, "chart_id")
            parts.append(styled_marks(marks, dots))
        else:
            parts.append(styled_marks(marks.withColumn("style", F.when((F.col("style") == "dashed") | ((F.col("style") == "wide_line") & (F.lit(kind) == "bar")), "plain").otherwise(F.col("style")))))
    marks = parts[0].unionByName(parts[1]).unionByName(parts[2])
    lines = grid(of.filter("style = 'grid'")).select("chart_id", F.lit(0).alias("series_no"), "px", "py")  # below every series
    palette = colours.select("chart_id", "series_no", "r", "g", "b").unionByName(of.filter("style = 'grid'").select("chart_id", F.lit(0).alias("series_no"), *(F.lit(GRID).alias(n) for n in "rgb")))
    px = painted(marks.unionByName(lines), palette).withColumn("series_no", F.nullif(F.col("series_no"), F.lit(0)))
    return px.join(of.select("chart_id", (F.col("style") == "dark").alias("dark")), "chart_id")


def degraded(px: DataFrame, speckle: int = 60, seed: int = 0) -> DataFrame:
    """Ink as lossy compression leaves it: each pixel may cast a pale gray speckle beside it (one in ``speckle``)."""
    key = F.concat_ws(",", "chart_id", "px", "py")
    u = draw(key, "speckle", seed)
    more = ["dark"] if "dark" in px.columns else []
    spots = px.filter(u % speckle == 0).select("chart_id", *more, (F.col("px") + u % 7 - 3).cast("int").alias("px"), (F.col("py") + (u % 11) - 5).cast("int").alias("py"), F.lit(None).cast("int").alias("series_no"), *(F.lit(c).alias(n) for c, n in zip((190, 184, 196), "rgb")))
    return px.unionByName(spots.join(px.select("chart_id", "px", "py"), ["chart_id", "px", "py"], "left_anti").dropDuplicates(["chart_id", "px", "py"]))


def blurred(img: np.ndarray) -> np.ndarray:
    """An image with soft edges: every pixel the mean of itself and its four neighbours."""
    p = np.pad(img.astype(np.uint16), ((1, 1), (1, 1), (0, 0)), mode="edge")
    return ((p[1:-1, 1:-1] + p[:-2, 1:-1] + p[2:, 1:-1] + p[1:-1, :-2] + p[1:-1, 2:]) // 5).astype(np.uint8)


def packed(px: DataFrame, background: tuple[int, int, int] = (255, 255, 255), blur: bool = False) -> DataFrame:
    """chart_id, width, height, channels, data: one image per chart; only one chart's ink meets in a task's memory.

    A column ``dark`` sets a chart's background to black; ``blur`` softens all edges.
    """
    def draw_one(key, table):
        img = np.empty((H, W, 3), np.uint8)
        img[:] = 0 if "dark" in table.column_names and table.column("dark")[0].as_py() else background
        x, y = table.column("px").to_numpy(), table.column("py").to_numpy()
        ok = (x >= 0) & (x < W) & (y >= 0) & (y < H)
        img[y[ok], x[ok]] = np.stack([table.column(n).to_numpy() for n in "rgb"], axis=1)[ok]
        if blur:
            img = blurred(img)
        return pa.table({"chart_id": pa.array([key[0].as_py()], pa.int64()), "width": pa.array([W], pa.int32()), "height": pa.array([H], pa.int32()), "channels": pa.array([3], pa.int32()), "data": pa.array([img.tobytes()], pa.binary())})

    return px.select("chart_id", "px", "py", "r", "g", "b", *(["dark"] if "dark" in px.columns else [])).groupBy("chart_id").applyInArrow(draw_one, "chart_id long, width int, height int, channels int, data binary")
