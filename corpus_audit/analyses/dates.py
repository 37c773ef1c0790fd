"""Documents per year, from reliable dates or estimated from index dates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def by_year(df: DataFrame, ts: str = "created") -> DataFrame:
    """corpus, yr, n, frac of the corpus's dated documents."""
    counted = df.filter(F.col(ts).isNotNull()).groupBy("corpus", F.year(ts).alias("yr")).agg(F.count("*").alias("n"))
    return counted.withColumn("frac", F.round(F.col("n") / F.sum("n").over(W.partitionBy("corpus")), 6))


def by_year_estimated(df: DataFrame, index_dates: DataFrame, key: str, ts: str = "created", sample: int = 10_000, seed: str = "y") -> DataFrame:
    """As ``by_year`` over a seeded sample of ids, each dated by the earlier of its first index date and its own.

    ``index_dates(key, first_seen)`` may lack ids and may hold several dates of one. The sample is
    drawn from ids alone, so nothing else of the other rows is read. The date is a lower bound.
    """
    order = F.md5(F.concat(F.lit(seed), F.col(key).cast("string")).cast("binary"))
    chosen = F.broadcast(df.select(key).orderBy(order, key).limit(sample))
    first = index_dates.join(chosen, key, "left_semi").groupBy(key).agg(F.min("first_seen").alias("first_seen"))
    dated = df.join(chosen, key, "left_semi").join(first, key, "left")
    return by_year(dated.select("corpus", F.least(F.col(ts), F.col("first_seen")).alias("__at")), "__at")
