"""An inverted index as a Spark table: term, doc_id, tf, positions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.text.tokenize import tokens

#: Positions of one term that one row holds at most; longer lists continue in further rows.
ROW_POSITIONS = 10_000


def build(df: DataFrame, fold: bool = False, mode: str = "unicode") -> DataFrame:
    """Postings of all documents; ``fold`` lower-cases terms. Null ids and texts have none."""
    text = F.lower("text") if fold else F.col("text")
    placed = df.filter(F.col("doc_id").isNotNull()).select("doc_id", F.posexplode(tokens(text, mode)).alias("pos", "term"))
    split = placed.groupBy("term", "doc_id", F.floor(F.col("pos") / ROW_POSITIONS).alias("part"))
    return split.agg(F.count("*").alias("tf"), F.array_sort(F.collect_list("pos")).alias("positions"))


def save(postings: DataFrame, name: str, buckets: int = 64) -> None:
    """Store bucketed and sorted by term, so that a lookup prunes to one bucket."""
    postings.write.bucketBy(buckets, "term").sortBy("term", "doc_id").mode("overwrite").saveAsTable(name)


def load(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name)
