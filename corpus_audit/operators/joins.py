"""Join forms that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, left_ts: str, right_ts: str, value: str) -> DataFrame:
    """Each left row with ``value`` and ``right_ts`` of the last right row of its key at or before its time.

    One shuffle on the key: both sides are stacked and a running last value is taken.
    """
    kind = dict(right.dtypes)[value]
    lhs = left.select(F.struct(*left.columns).alias("l"), F.col(by).alias("__k"), F.col(left_ts).alias("__t"), F.lit(1).alias("__side"), F.lit(None).cast(f"struct<at:timestamp,v:{kind}>").alias("__r"))
    rhs = right.select(F.lit(None).cast(left.select(F.struct(*left.columns).alias("l")).schema["l"].dataType).alias("l"), F.col(by).alias("__k"), F.col(right_ts).alias("__t"), F.lit(0).alias("__side"), F.struct(F.col(right_ts).alias("at"), F.col(value).alias("v")).alias("__r"))
    order = W.partitionBy("__k").orderBy("__t", "__side", F.col("__r.v")).rowsBetween(W.unboundedPreceding, 0)
    held = lhs.unionByName(rhs).withColumn("__last", F.last("__r", ignorenulls=True).over(order)).filter("__side = 1")
    return held.select("l.*", F.col("__last.at").alias(f"{right_ts}_before"), F.col("__last.v").alias(f"{value}_before"))


def range_join(points: DataFrame, ranges: DataFrame, point: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points with the ranges that hold them, by an equi join on blocks of ``width`` and a filter."""
    blocks = ranges.withColumn("__b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    placed = points.withColumn("__b", F.floor(F.col(point) / width))
    return placed.join(blocks, "__b").filter(F.col(point).between(F.col(lo), F.col(hi))).drop("__b")


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Inner join for a skewed key of the large side: its rows are dealt over ``salts`` copies of the small side's."""
    salted = large.withColumn("__s", F.pmod(F.xxhash64(*large.columns), F.lit(salts)))
    copies = small.withColumn("__s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)).cast("array<bigint>")))
    return salted.join(copies, [key, "__s"]).drop("__s")


def hash_order(column: str, seed: str) -> Column:
    """A reproducible random order of rows by a key."""
    return F.md5(F.concat(F.lit(seed), F.col(column).cast("string")).cast("binary"))


def hash_sample(df: DataFrame, key: str, size: int, seed: str = "h", per: str | None = None) -> DataFrame:
    """A fixed-size sample (per stratum) by hash order; ties by key."""
    if per is None:
        return df.orderBy(hash_order(key, seed), key).limit(size)
    order = W.partitionBy(per).orderBy(hash_order(key, seed), key)
    return df.withColumn("__r", F.row_number().over(order)).filter(F.col("__r") <= size).drop("__r")
