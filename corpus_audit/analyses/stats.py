"""Summary statistics of corpora."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpus_audit.text.tokenize import n_tokens


def prepared(df: DataFrame) -> DataFrame:
    """The core columns with n_chars, n_bytes, n_tokens and a digest: text is read once for many analyses."""
    text = F.coalesce("text", F.lit(""))
    return df.withColumns({"n_chars": F.length(text).cast("long"), "n_bytes": F.octet_length(text).cast("long"), "n_tokens": n_tokens("text"), "digest": F.unhex(F.md5(text.cast("binary")))})


def summary(df: DataFrame, by: str = "corpus") -> DataFrame:
    """Documents, bytes, characters, tokens, longest, shortest, blank documents and mean tokens per corpus."""
    text = F.coalesce("text", F.lit(""))
    slim = df.select(by, F.octet_length(text).alias("b"), F.length(text).alias("c"), n_tokens("text").alias("t"), (F.regexp_replace(text, r"[\s\p{Z}\x0B]+", "") == "").alias("blank"))
    return slim.groupBy(by).agg(
        F.count("*").alias("n_docs"), F.sum("b").alias("n_bytes"), F.sum("c").alias("n_chars"), F.sum("t").alias("n_tokens"), F.max("t").alias("max_tokens"),
        F.min("t").alias("min_tokens"), F.count_if("blank").alias("n_blank"), F.round(F.avg("t"), 6).alias("mean_tokens"),
    )


def subset_rollup(df: DataFrame) -> DataFrame:
    """Documents and tokens per (corpus, subset), per corpus and in all; null marks a total."""
    slim = df.select("corpus", "subset", n_tokens("text").alias("t"))
    return slim.rollup("corpus", "subset").agg(F.count("*").alias("n_docs"), F.sum("t").alias("n_tokens"))


def extremes(df: DataFrame, longest: bool = True) -> DataFrame:
    """The longest (shortest) document of each corpus; ties by the smaller id."""
    slim = df.select("corpus", "doc_id", n_tokens("text").alias("n_tokens"))
    key = F.struct(F.col("n_tokens") if longest else -F.col("n_tokens"), -F.col("doc_id"))
    return slim.groupBy("corpus").agg(F.max_by("doc_id", key).alias("doc_id"), (F.max if longest else F.min)("n_tokens").alias("n_tokens"))
