"""Connected components of an edge table by alternating large and small stars; every step is a join or an aggregate.

Where the caller sets a bound, edge tables up to it are counted first and solved on the driver, exactly as well."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stored


def _both(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))


def _tied(rows: DataFrame, store) -> tuple[DataFrame, DataFrame]:
    """Each (a, b) with ``m``, the smallest of a and its b; the minima are written so that a hub's join can be split."""
    low = store(rows.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("a", "m")), "star-minima")
    return rows.join(low.hint("merge"), "a"), low


def _stars(edges: DataFrame) -> bool:
    """Whether every node points at one root and no root points on."""
    if edges.join(edges.select(F.col("b").alias("a")).distinct().hint("merge"), "a", "left_semi").limit(1).count():
        return False
    return not edges.groupBy("a").agg(F.count("*").alias("n")).filter("n > 1").limit(1).count()


def rooted(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the edges (a, b) in order, and the smallest node that each one reaches."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    x, y, root = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while len(x):
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root = root[root]
        x, y = root[x], root[y]
        x, y = x[x != y], y[x != y]
    return nodes, nodes[root]


def components(edges: DataFrame, store=stored, few: int = 0) -> DataFrame:
    """node, component (its smallest node) of every node that has an edge; edges: a, b (long). ``store`` writes intermediates.

    ``few``: edges (of 16 bytes) up to which the table, which should be a stored one, is brought to the driver.
    """
    if few and edges.count() <= few:
        got = edges.filter("a <> b").select("a", "b").toArrow()
        nodes, least = rooted(*(got.column(n).to_numpy() for n in ("a", "b")))
        return edges.sparkSession.createDataFrame(pa.table({"node": nodes, "component": least}), "node long, component long")
    now = store(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    while not _stars(now):
        tied, low1 = _tied(_both(now), store)  # large star: larger neighbours move to the smallest
        large = store(tied.filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")), "large-star")
        tied, low2 = _tied(large, store)  # small star: smaller ones move
        small = tied.select(F.col("b").alias("x"), "m").unionByName(tied.select(F.col("a").alias("x"), "m")).filter("x <> m")
        new = store(small.select(F.col("x").alias("a"), F.col("m").alias("b")).distinct(), "small-star")
        for old in (now, low1, large, low2):
            discard(old)
        now = new
    nodes = now.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return nodes.unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
