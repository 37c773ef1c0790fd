"""Exact duplicates of texts and URLs by digests."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def clusters(df: DataFrame, column: str = "text", by: list[str] | None = None) -> DataFrame:
    """``by``, digest, size: 16 bytes per distinct value are shuffled, never the value."""
    digest = F.unhex(F.md5(F.col(column).cast("binary")))
    return df.filter(F.col(column).isNotNull()).groupBy(*(by or []), digest.alias("digest")).agg(F.count("*").alias("size"))


def stats(df: DataFrame, column: str = "text", by: str = "corpus") -> DataFrame:
    """Per corpus: documents, those in clusters of more than one (all members), their ratio, clusters, their share of distinct values, surplus copies."""
    size = F.col("size")
    dup, many = F.sum(F.when(size > 1, size).otherwise(0)), F.count_if(size > 1)
    return clusters(df, column, [by]).groupBy(by).agg(
        F.sum("size").alias("n_docs"), dup.alias("dup_docs"), F.round(dup / F.sum("size"), 6).alias("doc_ratio"), many.alias("dup_clusters"),
        F.round(many / F.count("*"), 6).alias("cluster_ratio"), (dup - many).alias("surplus"),
    )


def top(df: DataFrame, column: str = "text", k: int = 5, chars: int = 100) -> DataFrame:
    """rnk, cnt, excerpt of the k largest clusters; values are fetched for those only. Ties by digest."""
    best = clusters(df, column).filter("size > 1").orderBy(F.desc("size"), F.hex("digest")).limit(k)
    ranked = best.withColumn("rnk", F.row_number().over(W.orderBy(F.desc("size"), F.hex("digest"))))
    keyed = df.select(F.col(column).alias("v"), F.unhex(F.md5(F.col(column).cast("binary"))).alias("digest"))
    fetched = keyed.join(F.broadcast(ranked), "digest").groupBy("rnk", "size").agg(F.min(F.substring("v", 1, chars)).alias("excerpt"))
    return fetched.select("rnk", F.col("size").alias("cnt"), "excerpt")


def sizes(df: DataFrame, column: str = "text") -> DataFrame:
    """size, clusters, docs, cum_share: how many clusters have each size, and the share of duplicates from the largest down."""
    hist = clusters(df, column).filter("size > 1").groupBy("size").agg(F.count("*").alias("clusters"), F.sum("size").alias("docs"))
    down = W.orderBy(F.desc("size")).rowsBetween(W.unboundedPreceding, 0)
    whole = W.orderBy(F.desc("size")).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return hist.select("size", "clusters", "docs", F.round(F.sum("docs").over(down) / F.sum("docs").over(whole), 6).alias("cum_share"))


def cross_key(df: DataFrame, a: str, b: str, k: int = 25) -> DataFrame:
    """key, n, n_other: of the k values of ``a`` with most copies, the distinct values of ``b`` among the copies."""
    best = df.filter(F.col(a).isNotNull()).groupBy(F.col(a).alias("key")).agg(F.count("*").alias("n")).filter("n > 1").orderBy(F.desc("n"), "key").limit(k)
    return df.join(F.broadcast(best), df[a] == best["key"]).groupBy("key", "n").agg(F.countDistinct(b).alias("n_other"))


def key_bytes(df: DataFrame, col: str = "text") -> DataFrame:
    """corpus, string_bytes, digest_bytes, ratio: what the distinct keys weigh as strings and as 16-byte digests; only digests are shuffled."""
    slim = df.filter(F.col(col).isNotNull()).select("corpus", F.md5(F.col(col).cast("binary")).alias("digest"), F.octet_length(col).alias("b"))
    one = slim.groupBy("corpus", "digest").agg(F.first("b").alias("b"))
    return one.groupBy("corpus").agg(F.sum("b").alias("string_bytes"), (16 * F.count("*")).alias("digest_bytes"), F.round(F.sum("b") / (16 * F.count("*")), 6).alias("ratio"))
