"""Similarity of corpora by their most frequent n-grams."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def tops(counted: DataFrame, k: int) -> DataFrame:
    """corpus, gram, cnt, rnk of the k most frequent grams of each corpus, from (corpus, gram, cnt)."""
    order = W.partitionBy("corpus").orderBy(F.desc("cnt"), "gram")
    return counted.withColumn("rnk", F.row_number().over(order)).filter(F.col("rnk") <= k)


def rank_pairs(top: DataFrame, show: int = 1000, depth: int = 10_000) -> DataFrame:
    """corpus_a, corpus_b, gram, rank_a, rank_b: the first ``show`` grams of a with their rank in b (null beyond ``depth``)."""
    a = top.filter(F.col("rnk") <= show).select(F.col("corpus").alias("corpus_a"), "gram", F.col("rnk").alias("rank_a"))
    others = top.select(F.col("corpus").alias("corpus_b")).distinct()
    b = top.filter(F.col("rnk") <= depth).select(F.col("corpus").alias("corpus_b"), "gram", F.col("rnk").alias("rank_b"))
    paired = a.join(F.broadcast(others), F.col("corpus_a") != F.col("corpus_b"))  # as many rows as corpora
    return paired.join(b, ["corpus_b", "gram"], "left").select("corpus_a", "corpus_b", "gram", "rank_a", "rank_b")


def js(top: DataFrame, vocab: str = "intersection") -> DataFrame:
    """corpus_a, corpus_b, distance: square root of the Jensen-Shannon divergence (base 2) of each pair.

    The vocabulary is the intersection or the union of the two lists; shares are renormalised on
    it. Without common words the intersection's distance is null and the union's is 1.
    """
    sides = [top.select(F.col("corpus").alias(f"corpus_{x}"), "gram", F.col("cnt").alias(f"n_{x}")) for x in "ab"]
    names = [top.select(F.col("corpus").alias(f"corpus_{x}")).distinct() for x in "ab"]
    pairs = F.broadcast(names[0].join(F.broadcast(names[1]), F.col("corpus_a") < F.col("corpus_b")))
    left, right = pairs.join(sides[0], "corpus_a"), pairs.join(sides[1], "corpus_b")
    on = ["corpus_a", "corpus_b", "gram"]
    joined = left.join(right, on, "inner" if vocab == "intersection" else "full").na.fill(0, ["n_a", "n_b"])
    pair = W.partitionBy("corpus_a", "corpus_b")
    p, q = F.try_divide("n_a", F.sum("n_a").over(pair)), F.try_divide("n_b", F.sum("n_b").over(pair))
    shares = joined.select("corpus_a", "corpus_b", p.alias("p"), q.alias("q"))
    m = (F.col("p") + F.col("q")) / 2
    part = lambda x: F.when(F.col(x) > 0, F.col(x) * F.log2(F.col(x) / m)).otherwise(0.0)
    total = F.sum(part("p") + part("q")) / 2
    found = shares.groupBy("corpus_a", "corpus_b").agg(F.round(F.sqrt(F.greatest(F.lit(0.0), total)), 6).alias("distance"))
    return pairs.join(found, ["corpus_a", "corpus_b"], "left")


def js_mean(distances: DataFrame) -> DataFrame:
    """corpus, mean_distance to the others."""
    both = distances.select(F.col("corpus_a").alias("corpus"), "distance").union(distances.select("corpus_b", "distance"))
    return both.groupBy("corpus").agg(F.round(F.avg("distance"), 6).alias("mean_distance"))


def shared(top: DataFrame) -> DataFrame:
    """gram, n_corpora: grams in the lists of more than one corpus."""
    return top.groupBy("gram").agg(F.countDistinct("corpus").alias("n_corpora")).filter("n_corpora > 1")
