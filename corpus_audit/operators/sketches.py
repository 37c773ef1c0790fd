"""Spark's own sketches as a second approximate family beside hashed cells."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def distinct(df: DataFrame, key: str) -> DataFrame:
    """approx, hll, theta estimates of the distinct keys."""
    return df.agg(F.approx_count_distinct(key).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg(key)).alias("hll"), F.theta_sketch_estimate(F.theta_sketch_agg(key)).alias("theta"))


def top(df: DataFrame, key: str, k: int) -> DataFrame:
    """key, est: approximate most frequent keys in bounded memory."""
    found = df.selectExpr(f"explode(approx_top_k({key}, {k})) AS t")
    return found.select(F.col("t.item").alias(key), F.col("t.count").alias("est"))


def held(sketch: DataFrame, truth: DataFrame, key: str, total: int, eps: float) -> DataFrame:
    """key, within: whether the sketch's estimate of each key of ``truth(key, cnt)`` is no less than cnt, and at most ``eps * total`` more."""
    counter = sketch.sparkSession._jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(bytes(sketch.first()["sketch"]))
    rows = [(r[key], r["cnt"] <= counter.estimateCount(r[key]) <= r["cnt"] + eps * total) for r in truth.collect()]
    return sketch.sparkSession.createDataFrame(rows, f"`{key}` string, within boolean")


def frequencies(df: DataFrame, key: str, eps: float = 0.001, confidence: float = 0.99, seed: int = 1) -> DataFrame:
    """A count-min sketch of the keys, one binary value."""
    return df.agg(F.count_min_sketch(key, F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))
