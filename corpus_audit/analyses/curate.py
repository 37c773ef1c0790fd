"""Filters on what the analyses found, and the corpus card."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def drop_duplicates(df: DataFrame) -> DataFrame:
    """One document per text, the smallest id; rows of a digest are compared by id alone."""
    keyed = df.select("doc_id", F.unhex(F.md5(F.coalesce("text", F.lit("")).cast("binary"))).alias("digest"))
    first = keyed.groupBy("digest").agg(F.min("doc_id").alias("doc_id")).select("doc_id")
    return df.join(first, "doc_id", "left_semi")


def drop_blank(df: DataFrame) -> DataFrame:
    return df.filter(F.coalesce(F.regexp_replace("text", r"[\s\p{Z}\x0B]+", "") != "", F.lit(False)))


def drop_repeats(df: DataFrame, pattern: str = r"([^\w\s])\1{9,}") -> DataFrame:
    """Texts without long runs of one mark, the noise that tops lists of long n-grams."""
    return df.filter(~F.coalesce(F.col("text").rlike(pattern), F.lit(False)))


RULES = {"duplicates": drop_duplicates, "blank": drop_blank, "repeats": drop_repeats}


def apply(df: DataFrame, rules: list[str]) -> DataFrame:
    return reduce(lambda d, r: RULES[r](d), rules, df)


def card(results: dict[str, DataFrame], labels: dict[str, str] | None = None) -> DataFrame:
    """corpus, analysis, metric, value: wide per-corpus results as one long table.

    ``labels`` names the column that tells rows of one corpus apart, where a result has several;
    its value follows the metric's name.
    """
    labels = labels or {}

    def long(name: str, df: DataFrame) -> DataFrame:
        label = labels.get(name)
        metrics = [c for c, t in df.dtypes if c not in ("corpus", label) and t in ("bigint", "int", "double")]
        typed = df.select("corpus", *([label] if label else []), *(F.col(c).cast("double").alias(c) for c in metrics))
        rows = typed.unpivot(["corpus", label] if label else "corpus", metrics, "metric", "value")
        metric = F.concat_ws(" ", "metric", label) if label else F.col("metric")
        return rows.select("corpus", F.lit(name).alias("analysis"), metric.alias("metric"), F.round("value", 6).alias("value"))

    return reduce(DataFrame.unionByName, [long(k, v) for k, v in results.items()])
