"""Trips of the four stand-in networks: o, d, t, pax. Nulls, o = d and pax <= 0 go before any aggregate."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..functions import slots


def _t(spark, sf_dir, name, *cols):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*cols)


def valid(trips: DataFrame) -> DataFrame:
    return trips.where("o is not null and d is not null and t is not null and o <> d and pax > 0")


def _lines(spark: SparkSession, sf_dir: str, *extra: str) -> DataFrame:
    line = _t(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey", "l_quantity", *extra)
    orders = _t(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    cust, supp = _t(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), _t(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    return line.join(orders, line.l_orderkey == orders.o_orderkey).join(cust, F.col("o_custkey") == cust.c_custkey).join(supp, F.col("l_suppkey") == supp.s_suppkey)


def freight(spark, sf_dir) -> DataFrame:
    return valid(_lines(spark, sf_dir).select(F.col("s_nationkey").alias("o"), F.col("c_nationkey").alias("d"), (F.month("o_orderdate") - 1).alias("t"), F.col("l_quantity").cast("bigint").alias("pax")))


def months(spark, sf_dir) -> DataFrame:
    """The slot of every order: t."""
    return _t(spark, sf_dir, "orders", (F.month("o_orderdate") - 1).alias("t"))


def sizes(spark, sf_dir) -> DataFrame:
    """One row of the freight network: regions, slots, trips."""
    regions = _t(spark, sf_dir, "customer", "c_nationkey").agg(F.countDistinct("c_nationkey").cast("int").alias("regions"))
    return regions.crossJoin(months(spark, sf_dir).agg(F.countDistinct("t").cast("int").alias("slots"), F.count("*").alias("trips")))


def zones(spark, sf_dir) -> DataFrame:
    z = lambda n, k: (F.col(n) * 4 + F.col(k) % 4).cast("int")
    return valid(_lines(spark, sf_dir).select(z("s_nationkey", "s_suppkey").alias("o"), z("c_nationkey", "c_custkey").alias("d"), (F.month("o_orderdate") - 1).alias("t"), F.col("l_quantity").cast("bigint").alias("pax")))


def returns(spark, sf_dir) -> DataFrame:
    rows = _lines(spark, sf_dir, "l_linenumber", "l_returnflag").where("l_returnflag = 'R'")
    return valid(rows.select(F.col("s_nationkey").alias("o"), F.col("c_nationkey").alias("d"), F.floor((F.dayofyear("o_orderdate") - 1) / 14).cast("int").alias("t"), (50 + (F.col("l_orderkey") * 7 + F.col("l_linenumber") * 13) % 151).cast("bigint").alias("pax")))


def freight_quads(spark, sf_dir) -> DataFrame:
    """o, d, t, t_end, pax: the months of the order and of the shipment."""
    rows = _lines(spark, sf_dir, "l_shipdate")
    return valid(rows.select(F.col("s_nationkey").alias("o"), F.col("c_nationkey").alias("d"), (F.month("o_orderdate") - 1).alias("t"), (F.month("l_shipdate") - 1).alias("t_end"), F.col("l_quantity").cast("bigint").alias("pax")).where("t_end is not null"))


def events(spark, sf_dir) -> DataFrame:
    """user_id, event_id, ts (a timestamp), k (region), pax in cents."""
    ev = _t(spark, sf_dir, "events", "event_id", "ts", "user_id", "value", F.floor(F.get_json_object("props", "$.k").cast("int") / 4).cast("int").alias("k"))
    return ev.select("user_id", "event_id", F.col("ts").cast("timestamp").alias("ts"), "k", F.round(F.col("value") * 100).cast("bigint").alias("pax"))


def hops(spark, sf_dir) -> DataFrame:
    """Consecutive events of a user: o, d, ts, pax in cents."""
    ev = _t(spark, sf_dir, "events", "event_id", "ts", "user_id", "value", F.floor(F.get_json_object("props", "$.k").cast("int") / 4).cast("int").alias("k"))
    nxt = F.lead("k").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return ev.select(F.col("k").alias("o"), nxt.alias("d"), "ts", F.round(F.col("value") * 100).cast("bigint").alias("pax"))


def clicks(spark, sf_dir, weekday_classes: bool = False, bounds: list[int] | None = None, flow: str = "cents") -> DataFrame:
    rows = hops(spark, sf_dir)
    rows = rows if flow == "cents" else rows.withColumn("pax", F.when(F.col("pax") > 0, 1).cast("bigint"))  # a hop without cents is no trip here either
    t = slots.custom(F.col("ts"), bounds) if bounds is not None else slots.uniform(F.col("ts"))
    return valid(rows.select("o", "d", (slots.classed(F.col("ts"), t, 48) if weekday_classes else t).alias("t"), "pax"))
