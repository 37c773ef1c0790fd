"""Mean polarity of the sentences around demographic terms."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpus_audit.analyses.toxicity import sentences
from corpus_audit.text.tokenize import tokens


def _sentences(df: DataFrame, sample: float | None, seed: str) -> DataFrame:
    """doc_id, s, w: the lower-case tokens of each sentence; ``sample`` takes that share of documents by hash."""
    if sample is not None:
        df = df.filter(F.conv(F.substring(F.md5(F.concat(F.lit(seed), F.col("doc_id").cast("string")).cast("binary")), 1, 8), 16, 10).cast("long") < int(sample * 2**32))
    return df.select("doc_id", F.posexplode(sentences("text")).alias("s", "sentence")).select("doc_id", "s", F.transform(tokens("sentence"), lambda t: F.lower(t)).alias("w"))


def _terms(split: DataFrame) -> DataFrame:
    """doc_id, s, term: the distinct words and pairs of words of each sentence."""
    n = F.size("w") - 1
    pairs = F.when(n >= 1, F.zip_with(F.slice("w", 1, n), F.slice("w", 2, n), lambda a, b: F.concat(a, F.lit(" "), b))).otherwise(F.array().cast("array<string>"))
    return split.select("doc_id", "s", F.explode(F.array_distinct(F.concat("w", pairs))).alias("term"))


def polarity(split: DataFrame, lexicon: DataFrame) -> DataFrame:
    """doc_id, s, polarity: the mean over the sentence's words that the lexicon knows; sentences without any have 0."""
    words = split.select("doc_id", "s", F.explode("w").alias("term"))
    return words.join(F.broadcast(lexicon), "term", "left").groupBy("doc_id", "s").agg(F.coalesce(F.avg("score"), F.lit(0.0)).alias("polarity"))


def by_term(df: DataFrame, terms: DataFrame, lexicon: DataFrame, sample: float | None = None, seed: str = "d") -> DataFrame:
    """grp, term, n_sentences, mean_polarity over the sentences that hold the term."""
    split = _sentences(df, sample, seed)
    held = _terms(split).join(F.broadcast(terms), "term")
    scored = held.join(polarity(split, lexicon), ["doc_id", "s"])
    return scored.groupBy("grp", "term").agg(F.count("*").alias("n_sentences"), F.round(F.avg("polarity"), 6).alias("mean_polarity"))


def by_cooccurring_word(df: DataFrame, terms: DataFrame, lexicon: DataFrame, top: int = 10) -> DataFrame:
    """grp, term, n_words, mean_polarity of the ``top`` lexicon words that most often share a sentence with the term."""
    split = _sentences(df, None, "")
    held = _terms(split).join(F.broadcast(terms), "term")
    words = split.select("doc_id", "s", F.explode(F.array_distinct("w")).alias("word")).join(F.broadcast(lexicon.withColumnRenamed("term", "word")), "word")
    met = held.join(words, ["doc_id", "s"]).filter("word <> term").groupBy("grp", "term", "word", "score").agg(F.count("*").alias("n"))
    best = met.withColumn("r", F.row_number().over(W.partitionBy("grp", "term").orderBy(F.desc("n"), "word"))).filter(F.col("r") <= top)
    return best.groupBy("grp", "term").agg(F.count("*").alias("n_words"), F.round(F.avg("score"), 6).alias("mean_polarity"))
