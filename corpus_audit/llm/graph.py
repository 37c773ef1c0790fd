"""Connected components by alternating star contractions, all on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpus_audit.llm.common import discard, materialize


def _summary(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.hash("u", "v").cast("long")), F.sum((F.xxhash64("u", "v") % 1000003).cast("long"))).first())


def connected_components(edges: DataFrame) -> DataFrame:
    """``(u, v)`` undirected links of comparable ids to ``(node, component)``, the smallest id reachable.

    Every node with a link to another id is returned once; self links and repeated links are
    allowed, null ends are ignored, and an empty table gives an empty result. Each round links
    all larger neighbours of a node to its smallest neighbour, then all smaller ones, which halves
    distances; hubs are met by partial minima and by joins that adaptive execution may split.
    """
    now = edges.filter(F.col("u").isNotNull() & F.col("v").isNotNull() & (F.col("u") != F.col("v")))
    now = materialize(now.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "cc")
    seen = _summary(now)
    while seen[0]:
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.filter(F.col("v") > F.col("u")).join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.greatest("v", "m").alias("u"), F.least("v", "m").alias("v")))).alias("e"))
        nxt = materialize(small.select("e.u", "e.v").filter(F.col("u") != F.col("v")).distinct(), "cc")
        got = _summary(nxt)
        discard(now)
        now = nxt
        if got == seen:
            break
        seen = got
    stars = now.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component"))
    return stars.union(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
