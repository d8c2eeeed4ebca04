"""Chart families: the points behind charts, from the given tables.

Every family is (chart_id, series_key, x, y, ord) in integers: money in cents, time in days or microseconds, components in
billionths, so that sums and ranks do not depend on the order of addition.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.draws import draw
from .tables import table

COLUMNS = ("chart_id", "series_key", "x", "y")


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def day(c: str) -> Column:
    return F.unix_date(F.col(c).cast("date")).cast("long")


def micros(c: str) -> Column:
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast({c} as timestamp_ntz))")


def supplier(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem", "l_suppkey", "l_returnflag", "l_shipdate", "l_extendedprice")
    return rows.groupBy(F.col("l_suppkey").alias("chart_id"), F.col("l_returnflag").alias("series_key"), F.year("l_shipdate").cast("long").alias("x")).agg(F.sum(cents("l_extendedprice")).alias("y"))


def customer(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "orders", "o_custkey", "o_orderdate", "o_totalprice")
    return rows.select(F.col("o_custkey").alias("chart_id"), F.lit("all").alias("series_key"), day("o_orderdate").alias("x"), cents("o_totalprice").alias("y"))


def customer_status(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "orders", "o_custkey", "o_orderstatus", "o_orderdate", "o_totalprice")
    return rows.select(F.col("o_custkey").alias("chart_id"), F.col("o_orderstatus").alias("series_key"), day("o_orderdate").alias("x"), cents("o_totalprice").alias("y"))


def user(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "events", "user_id", "event_type", "ts", "value")
    return rows.select(F.col("user_id").alias("chart_id"), F.col("event_type").alias("series_key"), micros("ts").alias("x"), cents("value").alias("y"))


def brand(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "part", "p_brand", "p_type", "p_size", "p_retailprice")
    return rows.select(F.regexp_extract("p_brand", "([0-9]+)", 1).cast("long").alias("chart_id"), F.col("p_type").alias("series_key"), F.col("p_size").cast("long").alias("x"), cents("p_retailprice").alias("y"))


def nation(spark: SparkSession, d: str) -> DataFrame:
    orders = table(spark, d, "orders", "o_custkey", "o_orderstatus", "o_orderdate", "o_totalprice")
    who = table(spark, d, "customer", "c_custkey", "c_nationkey")
    rows = orders.join(who, orders.o_custkey == who.c_custkey)
    return rows.groupBy(F.col("c_nationkey").cast("long").alias("chart_id"), F.col("o_orderstatus").alias("series_key"), (F.year("o_orderdate") * 4 + F.quarter("o_orderdate")).cast("long").alias("x")).agg(F.sum(cents("o_totalprice")).alias("y"))


def embedding(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("i", "v"))
    return rows.select(F.col("vec_id").alias("chart_id"), F.lit("e").alias("series_key"), F.col("i").cast("long").alias("x"), F.round(F.col("v").cast("double") * 1e9).cast("long").alias("y"))


def cumulative(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "events", "event_id", "user_id", "event_type", "ts", "value")
    w = Window.partitionBy("user_id", "event_type").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return rows.select(F.col("user_id").alias("chart_id"), F.col("event_type").alias("series_key"), micros("ts").alias("x"), F.sum(cents("value")).over(w).alias("y"))


FAMILIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "supplier": supplier, "customer": customer, "customer_status": customer_status, "user": user, "brand": brand,
    "nation": nation, "embedding": embedding, "cumulative": cumulative,
}


def trend(points: DataFrame, seed: int = 0) -> DataFrame:
    """Any family with a slope of drawn sign added per series, which balances the classes: up, down or none."""
    key = F.concat_ws("|", F.col("chart_id"), F.col("series_key"))
    w = Window.partitionBy("chart_id", "series_key")
    sign = (draw(key, "slope", seed) % 3 - 1).cast("long")
    wide = points.withColumn("_span", F.max("y").over(w) - F.min("y").over(w) + 1).withColumn("_n", F.count("*").over(w)).withColumn("_i", F.row_number().over(w.orderBy("x", "y")))
    return wide.select("chart_id", "series_key", "x", F.expr("y").cast("long").alias("y0"), (F.col("y") + sign * F.floor(F.col("_span") * 2 * F.col("_i") / F.col("_n")).cast("long")).alias("y"), sign.cast("int").alias("slope")).drop("y0")


#: The same families as DuckDB SQL.
POINTS_SQL = {
    "supplier": "select l_suppkey as chart_id, l_returnflag as series_key, year(l_shipdate)::bigint as x, sum(round(l_extendedprice * 100)::bigint)::bigint as y from lineitem group by 1, 2, 3",
    "customer": "select o_custkey as chart_id, 'all' as series_key, date_diff('day', date '1970-01-01', o_orderdate::date)::bigint as x, round(o_totalprice * 100)::bigint as y from orders",
    "customer_status": "select o_custkey as chart_id, o_orderstatus as series_key, date_diff('day', date '1970-01-01', o_orderdate::date)::bigint as x, round(o_totalprice * 100)::bigint as y from orders",
    "user": "select user_id as chart_id, event_type as series_key, epoch_us(ts)::bigint as x, round(value * 100)::bigint as y from events",
    "brand": "select regexp_extract(p_brand, '([0-9]+)', 1)::bigint as chart_id, p_type as series_key, p_size::bigint as x, round(p_retailprice * 100)::bigint as y from part",
    "nation": "select c_nationkey::bigint as chart_id, o_orderstatus as series_key, (year(o_orderdate) * 4 + quarter(o_orderdate))::bigint as x, sum(round(o_totalprice * 100)::bigint)::bigint as y from orders join customer on o_custkey = c_custkey group by 1, 2, 3",
    "embedding": "select chart_id, 'e' as series_key, i as x, round(embedding[i + 1]::double * 1e9)::bigint as y from (select vec_id as chart_id, embedding, unnest(range(len(embedding))) as i from embeddings)",
    "cumulative": "select user_id as chart_id, event_type as series_key, epoch_us(ts)::bigint as x, (sum(round(value * 100)::bigint) over (partition by user_id, event_type order by ts, event_id rows between unbounded preceding and current row))::bigint as y from events",
}
