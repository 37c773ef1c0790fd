"""Countries of addresses by an interval join."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Addresses are joined on their first two numbers, then held against the range.
BLOCK = 1 << 16


def ip_number(ip: Column) -> Column:
    part = F.split(ip, r"\.")
    return sum((part[k].cast("long") * (1 << 8 * (3 - k)) for k in range(4)), F.lit(0).cast("long"))


def locate(addresses: DataFrame, ranges: DataFrame, ip: str = "ip") -> DataFrame:
    """``addresses`` with ``country``, null where no range holds the address; ranges(lo, hi, country) do not overlap."""
    blocks = ranges.select("lo", "hi", "country", F.explode(F.sequence(F.floor(F.col("lo") / BLOCK), F.floor(F.col("hi") / BLOCK))).alias("__b"))
    numbered = addresses.withColumn("__n", ip_number(F.col(ip))).withColumn("__b", F.floor(F.col("__n") / BLOCK))
    inside = (numbered["__b"] == blocks["__b"]) & F.col("__n").between(F.col("lo"), F.col("hi"))
    return numbered.join(blocks, inside, "left").drop(blocks["__b"]).drop("__b", "__n", "lo", "hi")


def countries(addresses: DataFrame, ranges: DataFrame, top: int = 9, drop_unknown: bool = False, sample: int | None = None, seed: str = "g") -> DataFrame:
    """country, n, share: the ``top`` countries and ``other``; addresses in no range are UN."""
    if sample is not None:
        addresses = addresses.orderBy(F.md5(F.concat(F.lit(seed), F.col("ip")).cast("binary"))).limit(sample)
    found = locate(addresses, ranges).select(F.coalesce("country", F.lit("UN")).alias("country"))
    if drop_unknown:
        found = found.filter("country <> 'UN'")
    counted = found.groupBy("country").agg(F.count("*").alias("n"))
    first = counted.orderBy(F.desc("n"), "country").limit(top).select("country", F.lit(True).alias("named"))
    named = counted.join(F.broadcast(first), "country", "left").select(F.when(F.col("named"), F.col("country")).otherwise("other").alias("country"), "n")
    total = counted.agg(F.sum("n").alias("total"))
    return named.groupBy("country").agg(F.sum("n").alias("n")).join(F.broadcast(total)).select("country", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))
