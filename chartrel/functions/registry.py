"""SQL names: ``visual_relation`` and ``spearman_agg`` over value arrays, ``label_within``, and the table function ``trace_columns``."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def _doubled_ranks(v: np.ndarray) -> np.ndarray:
    _, where, n = np.unique(v, return_inverse=True, return_counts=True)
    return (2 * (np.cumsum(n) - n) + n + 1)[where]


def rank_products(x: np.ndarray, y: np.ndarray) -> tuple[int, int, int]:
    """Sums of products of doubled mid-ranks about their mean: xy, xx, yy, as whole numbers of any size."""
    a, b = ((_doubled_ranks(np.asarray(v)) - len(v) - 1).astype(object) for v in (x, y))
    return (a * b).sum(), (a * a).sum(), (b * b).sum()


def rho(x: np.ndarray, y: np.ndarray) -> float | None:
    """Spearman correlation on mid-ranks; None where it is undefined."""
    if len(x) < 2:
        return None
    xy, xx, yy = rank_products(x, y)
    return None if xx * yy <= 0 else float(xy) / float(xx * yy) ** 0.5


def relation(x: np.ndarray, y: np.ndarray) -> str:
    """As ``truth.relations``, exact at the cut of 0.4."""
    if len(x) < 2:
        return "undefined"
    xy, xx, yy = rank_products(x, y)
    if xx == 0:
        return "undefined"
    if 25 * xy * xy <= 4 * xx * yy:
        return "neutral"
    return "increasing" if xy > 0 else "decreasing"


def register_sql(spark: SparkSession) -> None:
    """Registers the functions with the session's SQL."""

    @F.pandas_udf("string")
    def visual_relation(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([None if a is None or b is None else relation(a, b) for a, b in zip(x, y)])

    @F.pandas_udf("double")
    def spearman_agg(x: pd.Series, y: pd.Series) -> float:
        got = rho(x.to_numpy(), y.to_numpy())
        return float("nan") if got is None else got

    @F.udtf(returnType="x int, y double")
    class TraceColumns:
        def eval(self, xs, ys):
            """Mean y per column of a chart's pixels."""
            if xs is not None and ys is not None:
                x, y = np.array(xs), np.array(ys, float)
                for c in np.unique(x):
                    yield int(c), float(y[x == c].mean())

    spark.udf.register("visual_relation", visual_relation)
    spark.udf.register("spearman_agg", spearman_agg)
    spark.udtf.register("trace_columns", TraceColumns)
    spark.sql("create or replace temporary function label_within(a string, b string, k int) returns boolean return levenshtein(a, b) <= k")
