"""Baselines: a point extractor blind to colour, guesses, and the majority."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import draw
from . import truth as exact


def column_trace(px: DataFrame) -> DataFrame:
    """chart_id, x, y: per column the (upward, thousandfold) mean height of all ink, whatever its colour."""
    rows = px.groupBy("chart_id", "px").agg(F.sum("py").alias("s"), F.count("*").alias("n"))
    return rows.select("chart_id", F.col("px").cast("long").alias("x"), (-F.floor(F.col("s") * 1000 / F.col("n"))).cast("long").alias("y"))


def turning_points(trace: DataFrame) -> DataFrame:
    """Ends of a trace and the places where its slope changes sign; steps of no height take the sign before them."""
    w = Window.partitionBy("chart_id").orderBy("x")
    back, ahead = F.lag("y").over(w), F.lead("y").over(w)
    t = trace.select("*", F.signum((F.col("y") - back).cast("double")).alias("s0"), F.signum((ahead - F.col("y")).cast("double")).alias("s1"))
    t = t.withColumn("before", F.last(F.when(F.col("s0") != 0, F.col("s0")), ignorenulls=True).over(w))
    return t.filter(F.col("s0").isNull() | F.col("s1").isNull() | ((F.col("s1") != 0) & F.col("before").isNotNull() & (F.col("s1") != F.col("before")))).select("chart_id", "x", "y")


def interpolated(turns: DataFrame, step: int = 2) -> DataFrame:
    """chart_id, series_key, x, y every ``step`` columns between turning points, by integer interpolation from the one before."""
    w = Window.partitionBy("chart_id").orderBy("x")
    t = turns.select("chart_id", "x", "y", F.lead("x").over(w).alias("x1"), F.lead("y").over(w).alias("y1"))
    t = t.select("chart_id", "x", "y", F.coalesce("x1", F.col("x")).alias("x1"), F.coalesce("y1", F.col("y")).alias("y1"))
    last = F.when(F.col("x1") > F.col("x"), F.col("x1") - 1).otherwise(F.col("x"))
    g = t.withColumn("at", F.explode(F.sequence("x", last, F.lit(step).cast("long"))))
    run = F.when(F.col("x1") > F.col("x"), F.col("x1") - F.col("x")).otherwise(F.lit(1)).cast("long")
    y = F.col("y") + F.call_function("div", ((F.col("y1") - F.col("y")) * (F.col("at") - F.col("x"))).cast("long"), run)
    return g.select("chart_id", F.lit("all").alias("series_key"), F.col("at").alias("x"), y.cast("long").alias("y"))


def as_of(grid: DataFrame, turns: DataFrame) -> DataFrame:
    """Each grid place (chart_id, x) with the last turning point at or before it, by a union and one window, no range join."""
    u = grid.select("chart_id", "x", F.lit(None).cast("long").alias("ty"), F.lit(1).alias("k")).unionByName(turns.select("chart_id", "x", F.col("y").alias("ty"), F.lit(0).alias("k")))
    w = Window.partitionBy("chart_id").orderBy("x", "k").rowsBetween(Window.unboundedPreceding, 0)
    return u.withColumn("y", F.last("ty", ignorenulls=True).over(w)).filter("k = 1").select("chart_id", "x", "y")


def bar_heights(px: DataFrame) -> DataFrame:
    """chart_id, series_key, x, y: the top of the ink of every column."""
    return px.groupBy("chart_id", F.col("px").cast("long").alias("x")).agg((-F.min("py")).cast("long").alias("y")).select("chart_id", F.lit("all").alias("series_key"), "x", "y")


def point_extractor(px: DataFrame, truth: DataFrame, step: int = 2, plot_type: str = "line") -> DataFrame:
    """chart_id, series_no, relation: one trace per chart stands for each of its series, since colour is not seen.

    Lines are read by interpolated turning points, bars by their heights; scatter charts are refused.
    """
    if plot_type == "scatter":
        raise ValueError("the point extractor reads lines and bars only")
    points = bar_heights(px) if plot_type == "bar" else interpolated(turning_points(column_trace(px)), step)
    rel = exact.relations(points).select("chart_id", "relation")
    return truth.select("chart_id", "series_key", "series_no", "r", "g", "b").join(rel, "chart_id")


def followed_lines(px: DataFrame, reach: int = 12) -> DataFrame:
    """chart_id, series_key, x, y: lines followed from column to column by continuity, colours unseen.

    Each column's ink falls into runs. A line goes on to the run nearest to where it is heading; the nearest pairs are taken first and a run
    serves one line, unless fewer runs than lines are left, where lines overlap: then the rest share the nearest run, and who
    leaves it on which side is a guess. Lines without a run within ``reach`` rows end; runs that no line reaches start one.
    """
    import numpy as np
    import pyarrow as pa

    def one(key, table):
        x, y = table.column("px").to_numpy(), table.column("py").to_numpy()
        order = np.lexsort((y, x))
        x, y = x[order], y[order]
        lines, out = [], []  # a line: number, last height, last step, last column
        for c in np.unique(x).tolist():
            col = y[x == c]
            cut = np.flatnonzero(np.diff(col) > 1)
            runs = [(float(a + b) / 2, int(a), int(b)) for a, b in zip(col[np.concatenate(([0], cut + 1))], col[np.concatenate((cut, [len(col) - 1]))])]
            lines = [ln for ln in lines if c - ln[3] <= 2]
            pairs = sorted((abs(ln[1] + ln[2] - r[0]) - (r[2] - r[1]) / 2, i, j) for i, ln in enumerate(lines) for j, r in enumerate(runs))
            own, used = {}, set()
            for gap, i, j in pairs:
                if i not in own and j not in used and gap <= reach:
                    own[i] = j
                    used.add(j)
            for gap, i, j in pairs:
                if i not in own and gap <= 1:
                    own[i] = j
            for i, j in own.items():
                ln = lines[i]
                ln[1], ln[2], ln[3] = runs[j][0], max(-6.0, min(6.0, (runs[j][0] - ln[1]) / max(1, c - ln[3]))), c
                out.append((ln[0], c, int(-1000 * runs[j][0])))
            for j, r in enumerate(runs):
                if j not in used:
                    number = len({k for k, _, _ in out}) + 1
                    lines.append([number, r[0], 0.0, c])
                    out.append((number, c, int(-1000 * r[0])))
        n = {k: sum(o[0] == k for o in out) for k in {o[0] for o in out}}
        most = max(n.values(), default=0)
        out = [o for o in out if 4 * n[o[0]] >= most]  # crumbs are no lines
        return pa.table({"chart_id": pa.array([key[0].as_py()] * len(out), pa.int64()), "series_key": pa.array([str(o[0]) for o in out], pa.string()), "x": pa.array([o[1] for o in out], pa.int64()), "y": pa.array([o[2] for o in out], pa.int64())})

    return px.select("chart_id", "px", "py").distinct().groupBy("chart_id").applyInArrow(one, "chart_id long, series_key string, x long, y long")


def line_extractor(px: DataFrame) -> DataFrame:
    """chart_id, series_no, relation of every line that ``followed_lines`` makes out."""
    return exact.relations(followed_lines(px)).select("chart_id", F.col("series_key").cast("int").alias("series_no"), "relation")


def random_guess(series: DataFrame, seed: int = 0) -> DataFrame:
    """One of the three relations by a repeatable draw."""
    u = (draw(F.concat_ws("|", "chart_id", "series_key"), "guess", seed) % 3).cast("int") + 1
    return series.withColumn("relation", F.element_at(F.array(*map(F.lit, ("increasing", "decreasing", "neutral"))), u))


def majority(series: DataFrame, truth: DataFrame) -> DataFrame:
    """The commonest true relation for every series; ties to the first by name."""
    top = truth.filter("relation <> 'undefined'").groupBy("relation").agg(F.count("*").alias("n")).agg(F.min_by("relation", F.struct((-F.col("n")).alias("m"), "relation")).alias("relation"))
    return series.drop("relation").crossJoin(F.broadcast(top))  # one row


def text_only(train: DataFrame, test: DataFrame) -> DataFrame:
    """``test`` with ``guess``: the commonest training relation of series of the same ``token``, else of all; ties to the first by name.

    frames: relation, token and what else names a series. Text says nothing of a chart's shape: a lower bound for any reader of text.
    """
    first = lambda df, *by: df.groupBy(*by, "relation").agg(F.count("*").alias("n")).groupBy(*by).agg(F.min_by("relation", F.struct((-F.col("n")).alias("m"), "relation")).alias("best"))
    known = first(train, "token").withColumnRenamed("best", "own")
    return test.join(known, "token", "left").crossJoin(F.broadcast(first(train))).withColumn("guess", F.coalesce("own", "best")).drop("own", "best")  # one row
