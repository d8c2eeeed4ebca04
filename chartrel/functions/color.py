"""Colour algebra on the scales hue 0..179 (half degrees), saturation and value 0..255; integer arithmetic throughout."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _div(a: Column, b: Column) -> Column:
    """Integer quotient of non-negative numbers."""
    return F.floor(a / b).cast("int")


def hsv(r: Column, g: Column, b: Column) -> tuple[Column, Column, Column]:
    """Hue, saturation, value columns; ties of the largest channel go to red, then green."""
    v, low = F.greatest(r, g, b), F.least(r, g, b)
    d = v - low
    s = F.when(v == 0, 0).otherwise(_div(510 * d + v, 2 * v))
    # Hue in half degrees, rounded: 30 per sector, offset kept positive by a full turn of 180.
    at = F.when(v == r, 360 * d + 60 * (g - b)).when(v == g, 120 * d + 60 * (b - r)).otherwise(240 * d + 60 * (r - g))
    h = F.when(d == 0, 0).otherwise(_div(at + d, 2 * d) % 180)
    # Never null, so that no null test is derived from joins and pushed, written out, below the projection.
    return tuple(F.coalesce(c.cast("int"), F.lit(-1)) for c in (h, s, v))


def with_hsv(px: DataFrame) -> DataFrame:
    h, s, v = hsv(F.col("r"), F.col("g"), F.col("b"))
    return px.withColumns({"h": h, "s": s, "v": v})


def full_hue(h: Column) -> tuple[Column, Column, Column]:
    """RGB of a hue at full saturation and value: six linear ramps of 30 half degrees."""
    up = _div((h % 30) * 255 + 15, F.lit(30))
    down = 255 - up
    k = _div(h, F.lit(30))
    z, full = F.lit(0), F.lit(255)
    sel = lambda *c: F.element_at(F.array(*(x.cast("int") for x in c)), k + 1)
    return sel(full, down, z, z, up, full), sel(up, full, full, down, z, z), sel(z, z, up, full, full, down)


def np_hsv(rgb: np.ndarray) -> np.ndarray:
    """The same for an (..., 3) array."""
    r, g, b = (rgb[..., i].astype(np.int64) for i in range(3))
    v, low = np.maximum(np.maximum(r, g), b), np.minimum(np.minimum(r, g), b)
    d = v - low
    s = np.where(v == 0, 0, (510 * d + v) // np.maximum(2 * v, 1))
    at = np.where(v == r, 360 * d + 60 * (g - b), np.where(v == g, 120 * d + 60 * (b - r), 240 * d + 60 * (r - g)))
    h = np.where(d == 0, 0, (at + d) // np.maximum(2 * d, 1) % 180)
    return np.stack((h, s, v), axis=-1)


def np_full_hue(h: np.ndarray) -> np.ndarray:
    h = h.astype(np.int64)
    up = ((h % 30) * 255 + 15) // 30
    down, z, full = 255 - up, np.zeros_like(h), np.full_like(h, 255)
    k = h // 30
    r = np.choose(k, [full, down, z, z, up, full])
    g = np.choose(k, [up, full, full, down, z, z])
    b = np.choose(k, [z, z, up, full, full, down])
    return np.stack((r, g, b), axis=-1)


#: DuckDB expressions of hue, saturation and value over integer columns r, g, b (int64).
HSV_SQL = """
  greatest(r, g, b) as v,
  case when greatest(r, g, b) = 0 then 0 else (510 * (greatest(r, g, b) - least(r, g, b)) + greatest(r, g, b)) // (2 * greatest(r, g, b)) end as s,
  case when greatest(r, g, b) = least(r, g, b) then 0 else
    ((case when greatest(r, g, b) = r then 360 * (greatest(r, g, b) - least(r, g, b)) + 60 * (g - b)
           when greatest(r, g, b) = g then 120 * (greatest(r, g, b) - least(r, g, b)) + 60 * (b - r)
           else 240 * (greatest(r, g, b) - least(r, g, b)) + 60 * (r - g) end
      + (greatest(r, g, b) - least(r, g, b))) // (2 * (greatest(r, g, b) - least(r, g, b)))) % 180 end as h"""
