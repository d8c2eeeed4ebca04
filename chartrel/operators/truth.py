"""Ground truth: Spearman rank correlation per series and its trichotomy, decided in exact integers."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

UP, DOWN, FLAT, NONE = "increasing", "decreasing", "neutral", "undefined"
SERIES = ("chart_id", "series_key")
#: Products of ranks are summed as two longs, their bits above and below this one.
LOW_BITS = 31


def rank_sums(points: DataFrame, by: tuple[str, ...] = SERIES) -> DataFrame:
    """n and, about their means, the sums of products of doubled mid-ranks of x and y (xy, xx, yy): one exchange, two sorts.

    Exact up to a thousand million points a series. The mean of doubled mid-ranks is n + 1, ties or not.
    """
    def doubled(c: str) -> Column:
        w = Window.partitionBy(*by).orderBy(c)
        return (2 * F.rank().over(w) + F.count("*").over(w.rangeBetween(0, 0)) - 1).cast("long")

    ranked = points.select(*by, doubled("x").alias("a"), doubled("y").alias("b"))
    products = {"xy": F.col("a") * F.col("b"), "xx": F.col("a") * F.col("a"), "yy": F.col("b") * F.col("b")}
    halves = [e for name, p in products.items() for e in (F.sum(F.shiftright(p, LOW_BITS)).alias(f"{name}_high"), F.sum(p.bitwiseAND(F.lit((1 << LOW_BITS) - 1))).alias(f"{name}_low"))]
    sums = ranked.groupBy(*by).agg(F.count("*").alias("n"), *halves)
    whole = lambda c: F.col(c).cast("decimal(19,0)")
    mean = ((whole("n") + 1) * (whole("n") + 1)).cast("decimal(20,0)")
    about = lambda s: (whole(f"{s}_high") * F.lit(1 << LOW_BITS) + whole(f"{s}_low") - whole("n") * mean).cast("decimal(30,0)")
    return sums.select(*by, "n", *(about(s).alias(s) for s in products))


def against(num: Column, vx: Column, vy: Column, ratio: tuple[int, int]) -> Column:
    """Sign of num^2 / (vx vy) less the square of p / q, exactly: integers of up to 30 digits, multiplied in halves of 15."""
    p, q = ratio
    base = F.lit(10**15).cast("decimal(16,0)")

    def halves(v: Column) -> tuple[Column, Column]:
        low = F.pmod(v, base)
        return ((v - low) / base).cast("decimal(15,0)"), low.cast("decimal(15,0)")

    (a, b), (c, d), (e, f) = halves(F.abs(num)), halves(vx), halves(vy)
    left, right = F.lit(q * q).cast("decimal(4,0)"), F.lit(p * p).cast("decimal(4,0)")
    wide = lambda v: v.cast("decimal(36,0)")
    digits = [wide(left * wide(x)) - wide(right * wide(y)) for x, y in ((b * b, d * f), (2 * a * b, c * f + d * e), (a * a, c * e))]
    rest, carry = [], F.lit(0).cast("decimal(36,0)")
    for v in digits[:2]:
        v = wide(v + carry)
        low = F.pmod(v, base)
        rest.append(low)
        carry = wide((v - low) / base)
    top = wide(digits[2] + carry)
    return F.when(top != 0, F.signum(top.cast("double"))).when((rest[0] > 0) | (rest[1] > 0), F.lit(1.0)).otherwise(F.lit(0.0)).cast("int")


def spearman(points: DataFrame, by: tuple[str, ...] = SERIES, ties: str = "mid") -> DataFrame:
    """by, n, xy, xx, yy (rho = xy / sqrt(xx yy)), rho; ``ties="none"`` is the formula for distinct ranks."""
    if ties == "none":
        def plain(c: str) -> Column:
            return F.row_number().over(Window.partitionBy(*by).orderBy(c, *(x for x in ("x", "y") if x != c)))

        d = points.select(*by, (plain("x") - plain("y")).cast("long").alias("d")).groupBy(*by).agg(F.count("*").alias("n"), F.sum(F.col("d") * F.col("d")).alias("dd"))
        return d.withColumn("rho", F.when(F.col("n") > 1, 1 - 6 * F.col("dd") / (F.col("n") * (F.col("n") * F.col("n") - 1))))
    s = rank_sums(points, by)
    root = F.sqrt(F.col("xx").cast("double")) * F.sqrt(F.col("yy").cast("double"))
    return s.withColumn("rho", F.when((F.col("xx") > 0) & (F.col("yy") > 0), F.col("xy").cast("double") / root))


def classified(rho: DataFrame, cut: tuple[int, int] = (2, 5)) -> DataFrame:
    """``relation`` by rho beyond +-cut (a ratio), strictly; constant y is neutral, under two points or constant x undefined."""
    beyond = against(F.col("xy"), F.col("xx"), F.col("yy"), cut) > 0
    label = F.when((F.col("n") < 2) | (F.col("xx") == 0), NONE).when(F.col("yy") == 0, FLAT).when(beyond & (F.col("xy") > 0), UP).when(beyond & (F.col("xy") < 0), DOWN).otherwise(FLAT)
    return rho.withColumn("relation", label)


def relations(points: DataFrame, cut: tuple[int, int] = (2, 5)) -> DataFrame:
    """chart_id, series_key, n, rho, relation of every series."""
    return classified(spearman(points), cut).select(*SERIES, "n", F.round("rho", 6).alias("rho"), "relation")


# Registry of relation functions: name -> what makes (chart_id, series_key, label) of points.
THETA: dict[str, Callable[[DataFrame], DataFrame]] = {}


def register(name: str, builder: Callable[[DataFrame], DataFrame]) -> None:
    """Adds a relation function; it gets points and returns (chart_id, series_key, label)."""
    THETA[name] = builder


def apply(points: DataFrame, names: tuple[str, ...]) -> DataFrame:
    """chart_id, series_key, theta, label for each named function."""
    out = None
    for name in names:
        got = THETA[name](points).select(*SERIES, F.lit(name).alias("theta"), "label")
        out = got if out is None else out.unionByName(got)
    return out


def _sign(c: Column) -> Column:
    return F.when(c > 0, UP).when(c < 0, DOWN).otherwise(FLAT)


def slope(points: DataFrame) -> DataFrame:
    """Sign of the least-squares slope, by exact sums about the first x and y."""
    w = Window.partitionBy(*SERIES)
    p = points.withColumn("u", (F.col("x") - F.min("x").over(w)).cast("decimal(19,0)")).withColumn("v", (F.col("y") - F.min("y").over(w)).cast("decimal(18,0)"))
    s = p.groupBy(*SERIES).agg(F.count("*").alias("n"), F.sum((F.col("u") * F.col("v")).cast("decimal(30,0)")).alias("uv"), F.sum("u").alias("su"), F.sum("v").alias("sv"))
    lead = F.col("n").cast("double") * F.col("uv").cast("double") - F.col("su").cast("double") * F.col("sv").cast("double")
    exact = (F.col("n").cast("decimal(8,0)") * F.col("uv").cast("decimal(30,0)")).cast("decimal(38,0)") - (F.col("su").cast("decimal(19,0)") * F.col("sv").cast("decimal(19,0)")).cast("decimal(38,0)")
    return s.withColumn("label", F.coalesce(_sign(exact), _sign(lead)))


def pearson(points: DataFrame, cut: tuple[int, int] = (2, 5)) -> DataFrame:
    """Trichotomy of the product-moment correlation: exact sums about the least x and y, compared in doubles."""
    w = Window.partitionBy(*SERIES)
    p = points.withColumn("u", (F.col("x") - F.min("x").over(w)).cast("decimal(19,0)")).withColumn("v", (F.col("y") - F.min("y").over(w)).cast("decimal(18,0)"))
    m = lambda a, b: F.sum((F.col(a) * F.col(b)).cast("decimal(30,0)"))
    s = p.groupBy(*SERIES).agg(F.count("*").cast("double").alias("n"), *(F.sum(c).cast("double").alias(f"s{c}") for c in "uv"), *(m(a, b).cast("double").alias(a + b) for a, b in ("uv", "uu", "vv")))
    num = F.col("n") * F.col("uv") - F.col("su") * F.col("sv")
    vx, vy = F.col("n") * F.col("uu") - F.col("su") * F.col("su"), F.col("n") * F.col("vv") - F.col("sv") * F.col("sv")
    beyond = F.lit(float(cut[1] ** 2)) * num * num > F.lit(float(cut[0] ** 2)) * vx * vy
    return s.withColumn("label", F.when((F.col("n") < 2) | (vx <= 0), NONE).when(vy <= 0, FLAT).when(beyond, _sign(num)).otherwise(FLAT))


def concordance(x, y) -> int:
    """Concordant less discordant pairs of one series; pairs equal in x count nothing. Ranks are counted level by level of a merge, n log n."""
    import numpy as np

    def below(v: np.ndarray, strict: bool) -> int:  # pairs i < j with v[i] < v[j] (or <=), by doubling runs that are sorted already
        total, n, size = 0, len(v), 1
        v = v.copy()
        while size < n:
            for lo in range(0, n, 2 * size):
                left, right = v[lo : lo + size], v[lo + size : lo + 2 * size]
                total += int(np.searchsorted(left, right, side="left" if strict else "right").sum())
                v[lo : lo + 2 * size] = np.sort(v[lo : lo + 2 * size], kind="stable")
            size *= 2
        return total

    order = np.lexsort((-y, x))  # equal x with falling y: never counted as rising
    up = below(y[order], True)
    order = np.lexsort((y, x))
    down = below(-y[order], True)
    return up - down


def kendall(points: DataFrame) -> DataFrame:
    """Sign of concordant less discordant pairs of each series, one series at a time in n log n."""
    import pyarrow as pa

    def one(key, table):
        s = concordance(table.column("x").to_numpy(), table.column("y").to_numpy())
        return pa.table({"chart_id": [key[0].as_py()], "series_key": [key[1].as_py()], "s": [s]}, schema=pa.schema([("chart_id", pa.int64()), ("series_key", pa.string()), ("s", pa.int64())]))

    got = points.select(F.col("chart_id").cast("long").alias("chart_id"), "series_key", F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"))
    return got.groupBy(*SERIES).applyInArrow(one, "chart_id long, series_key string, s long").withColumn("label", _sign(F.col("s")))


def monotone(points: DataFrame) -> DataFrame:
    """Strictly monotone in the order of x."""
    w = Window.partitionBy(*SERIES).orderBy("x", "y")
    step = points.select(*SERIES, (F.col("y") - F.lag("y").over(w)).alias("d"))
    s = step.groupBy(*SERIES).agg(F.min("d").alias("lo"), F.max("d").alias("hi"))
    return s.withColumn("label", F.when(F.col("lo") > 0, UP).when(F.col("hi") < 0, DOWN).otherwise(FLAT))


register("corr3", lambda p: relations(p).withColumnRenamed("relation", "label"))
register("slope", slope)
register("kendall", kendall)
register("pearson", pearson)
register("monotone", monotone)


def relations_sql(points: str) -> str:
    """DuckDB SQL of ``relations`` for a points query."""
    return f"""
    with p as ({points}),
    r as (select chart_id, series_key, x, y,
            (2 * rank() over (partition by chart_id, series_key order by x) + count(*) over (partition by chart_id, series_key, x) - 1)::hugeint as a,
            (2 * rank() over (partition by chart_id, series_key order by y) + count(*) over (partition by chart_id, series_key, y) - 1)::hugeint as b from p),
    s as (select chart_id, series_key, count(*)::hugeint as n, sum(a) as sa, sum(b) as sb, sum(a * b) as sab, sum(a * a) as saa, sum(b * b) as sbb from r group by 1, 2),
    t as (select *, n * sab - sa * sb as num, n * saa - sa * sa as va, n * sbb - sb * sb as vb from s)
    select chart_id, series_key, n::bigint as n, case when va > 0 and vb > 0 then round(num::double / sqrt((va * vb)::double), 6) end as rho,
      case when n < 2 or va = 0 then 'undefined' when vb = 0 then 'neutral'
           when num > 0 and 25 * num * num > 4 * va * vb then 'increasing'
           when num < 0 and 25 * num * num > 4 * va * vb then 'decreasing' else 'neutral' end as relation
    from t"""
