"""Length distributions, medians, outliers and templates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpus_audit.text.tokenize import n_tokens


def length(unit: str = "chars") -> Column:
    return F.length(F.coalesce("text", F.lit(""))).cast("long") if unit == "chars" else n_tokens("text")


def histogram(df: DataFrame, unit: str = "chars") -> DataFrame:
    """length, n, share."""
    counted = df.select(length(unit).alias("length")).groupBy("length").agg(F.count("*").alias("n"))
    total = counted.agg(F.sum("n").alias("total"))
    return counted.join(F.broadcast(total)).select("length", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))


def log_histogram(df: DataFrame, unit: str = "chars") -> DataFrame:
    """corpus, bin, n: bins of ten to a decade, by floor(10 log10); empty texts are bin -1."""
    n = length(unit)
    slim = df.select("corpus", n.alias("n")).select("corpus", F.when(F.col("n") > 0, F.floor(F.round(F.log10(F.col("n").cast("double")) * 10, 6))).otherwise(-1).cast("long").alias("bin"))
    return slim.groupBy("corpus", "bin").agg(F.count("*").alias("n"))


def outliers(hist: DataFrame, radius: int = 10, ratio: float = 5, min_n: int = 3) -> DataFrame:
    """length, n, neighbour_mean: lengths at least ``ratio`` times as common as the mean of the lengths around.

    Lengths that no document has count as zero, so the mean is over 2 * radius lengths. The
    histogram has one row per length, and its window is over those few rows.
    """
    around = W.orderBy("length").rangeBetween(-radius, radius)
    scored = hist.select("length", "n", ((F.sum("n").over(around) - F.col("n")) / (2.0 * radius)).alias("m"))
    return scored.filter((F.col("n") >= min_n) & (F.col("n") >= ratio * F.col("m"))).select("length", "n", F.round("m", 6).alias("neighbour_mean"))


def medians(df: DataFrame, exact: bool = True) -> DataFrame:
    """corpus, median_tokens, median_chars; inexact ones by a sketch."""
    slim = df.select("corpus", length("tokens").alias("t"), length("chars").alias("c"))
    cut = F.median if exact else (lambda c: F.percentile_approx(c, 0.5, 10_000).cast("double"))
    return slim.groupBy("corpus").agg(cut("t").alias("median_tokens"), cut("c").alias("median_chars"))


def templates(df: DataFrame, lengths: DataFrame, chars: int = 60) -> DataFrame:
    """template, n: texts of the given lengths grouped by their beginning with digit runs masked."""
    sized = df.withColumn("length", length("chars")).join(lengths.select("length").distinct(), "length", "left_semi")
    return sized.groupBy(F.substring(F.regexp_replace("text", r"[0-9]+", "0"), 1, chars).alias("template")).agg(F.count("*").alias("n")).filter("n > 1")
