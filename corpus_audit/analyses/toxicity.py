"""Toxic language by a lexicon and by a linear classifier over sentences."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.ml.classification import LinearSVC
from pyspark.ml.feature import CountVectorizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpus_audit.functions.lexicons import OFFENSIVE
from corpus_audit.text.tokenize import n_tokens, tokens

SENTENCE = r"[^.!?\n]+[.!?]*"
FEATURES = 1 << 18
FOLDS, HELD, JUDGE = 5, 0, 1


def sentences(text: Column | str = "text") -> Column:
    parts = F.regexp_extract_all(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), F.lit(SENTENCE), F.lit(0))
    return F.filter(F.transform(parts, lambda s: F.trim(s)), lambda s: s != "")


def matches(df: DataFrame, lexicon: DataFrame) -> DataFrame:
    """doc_id, corpus, category, n: mentions of the terms, without regard to case; terms of two words by bigrams.

    Tokens are counted per document before they meet the broadcast lexicon.
    """
    words = df.select("doc_id", "corpus", F.transform(tokens("text"), lambda t: F.lower(t)).alias("w"))
    pairs = F.when(F.size("w") >= 2, F.zip_with(F.slice("w", 1, F.size("w") - 1), F.slice("w", 2, F.size("w") - 1), lambda a, b: F.concat(a, F.lit(" "), b))).otherwise(F.array().cast("array<string>"))
    terms = words.select("doc_id", "corpus", F.explode(F.concat("w", pairs)).alias("term"))
    return terms.join(F.broadcast(lexicon), "term").groupBy("doc_id", "corpus", "category").agg(F.count("*").alias("n"))


def taxonomy(df: DataFrame, lexicon: DataFrame) -> DataFrame:
    """corpus, category, mentions, per_token."""
    found = matches(df, lexicon).groupBy("corpus", "category").agg(F.sum("n").alias("mentions"))
    total = df.select("corpus", n_tokens("text").alias("t")).groupBy("corpus").agg(F.sum("t").alias("t"))
    return found.join(total, "corpus").select("corpus", "category", "mentions", F.round(F.col("mentions") / F.col("t"), 9).alias("per_token"))


def toxic_ids(df: DataFrame, lexicon: DataFrame) -> DataFrame:
    """Documents with a term of an offensive category."""
    return matches(df, lexicon).filter(F.col("category").isin(*OFFENSIVE)).select("doc_id").distinct()


def documents(df: DataFrame, lexicon: DataFrame) -> DataFrame:
    """corpus, n_docs, n_toxic, pct."""
    flagged = df.select("doc_id", "corpus").join(toxic_ids(df, lexicon).withColumn("hit", F.lit(1)), "doc_id", "left")
    return flagged.groupBy("corpus").agg(F.count("*").alias("n_docs"), F.count("hit").alias("n_toxic"), F.round(100 * F.count("hit") / F.count("*"), 6).alias("pct"))


def quality(predicted: DataFrame, labels: DataFrame) -> DataFrame:
    """tp, fp, fn, tn of predicted ids among the labelled documents."""
    hit = labels.select("doc_id", "toxic").join(predicted.select("doc_id", F.lit(1).alias("hit")).distinct(), "doc_id", "left")
    yes, said = F.col("toxic") == 1, F.col("hit").isNotNull()
    return hit.agg(F.count_if(said & yes).alias("tp"), F.count_if(said & ~yes).alias("fp"), F.count_if(~said & yes).alias("fn"), F.count_if(~said & ~yes).alias("tn"))


def held_out(key: str = "doc_id") -> Column:
    """The fold (id modulo FOLDS is HELD) whose labels training never sees."""
    return F.coalesce(F.pmod(F.col(key), F.lit(FOLDS)) == HELD, F.lit(False))


def _lower_tokens(text: Column | str) -> Column:
    return tokens(F.lower(F.col(text) if isinstance(text, str) else text))


def train(df: DataFrame, labels: DataFrame) -> dict[str, float]:
    """Weights of a linear support vector machine over a sentence's words, and its intercept under the empty word; the held-out fold is left out.

    Labels are of documents: the sentences of a toxic one stand for it, both classes weigh the same, and the intercept is moved
    so that the documents' most toxic sentences part those of a second fold (JUDGE) best, which the weights never saw. The vocabulary is bounded: the FEATURES
    words in most sentences, of two at least.
    """
    known = labels.filter(~held_out() & F.col("toxic").isin(0, 1)).groupBy("doc_id").agg(F.max("toxic").cast("double").alias("label"))
    rows = df.select("doc_id", "text").join(known, "doc_id")
    judge = F.pmod(F.col("doc_id"), F.lit(FOLDS)) == JUDGE
    words = rows.filter(~judge).select("label", F.explode(sentences("text")).alias("s")).select("label", F.array_distinct(_lower_tokens("s")).alias("words")).persist()
    counts = {r["label"]: r["n"] for r in words.groupBy("label").agg(F.count("*").alias("n")).collect()}
    if len(counts) < 2:
        words.unpersist()
        return {"": -1.0}
    vectors = CountVectorizer(inputCol="words", outputCol="features", vocabSize=FEATURES, minDF=2.0, binary=True).fit(words)
    balanced = vectors.transform(words).withColumn("w", F.when(F.col("label") == 1, F.lit(counts[0.0] / counts[1.0])).otherwise(F.lit(1.0)))
    model = LinearSVC(maxIter=20, regParam=0.001, weightCol="w", aggregationDepth=2).fit(balanced)
    words.unpersist()
    weights = {"": 0.0} | {w: float(x) for w, x in zip(vectors.vocabulary, model.coefficients.toArray(), strict=True) if x}
    # The cut: hits and size of what lies above each score.
    scored = classify(rows.filter(judge), weights).join(known, "doc_id").groupBy("score").agg(F.sum("label").alias("hits"), F.count("*").alias("n"))
    above = W.orderBy(F.desc("score"))
    total = known.filter(judge).agg(F.coalesce(F.sum("label"), F.lit(0.0))).first()[0]
    f1 = 2 * F.sum("hits").over(above) / (F.sum("n").over(above) + total)
    below = F.coalesce(F.lead("score").over(above), F.col("score") - 1)
    best = scored.select("score", ((F.col("score") + below) / 2).alias("cut"), f1.alias("f1")).orderBy(F.desc("f1"), F.desc("score")).first()
    return weights | {"": -best["cut"] if best else -1.0}


def classify(df: DataFrame, weights: dict[str, float]) -> DataFrame:
    """doc_id, toxic, score: 1 if the most toxic sentence of the document lies above the machine's plane. Sentences are scored within the row."""
    spark = df.sparkSession
    shared = spark.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = pa.array([w for w in shared.value if w], type=pa.string())
        weight = np.asarray([x for w, x in shared.value.items() if w] + [0.0])
        for batch in batches:
            parts = batch.column("sentences")
            words = parts.flatten()
            flat = words.flatten()
            at = pc.index_in(flat, value_set=known).fill_null(len(weight) - 1).to_numpy(zero_copy_only=False)
            sums = np.concatenate([[0.0], np.cumsum(weight[at])])
            ends = np.concatenate([[0], np.cumsum(pc.list_value_length(words).to_numpy(zero_copy_only=False))]).astype(np.int64)
            score = sums[ends[1:]] - sums[ends[:-1]] + shared.value[""]
            size = pc.list_value_length(parts).to_numpy(zero_copy_only=False).astype(np.int64)
            best = np.full(batch.num_rows, -np.inf)
            np.maximum.at(best, np.repeat(np.arange(batch.num_rows), size), score)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array((best > 0).astype(np.int32)), pa.array(best)], names=["doc_id", "toxic", "score"])

    cut = df.select(F.col("doc_id").cast("long").alias("doc_id"), F.transform(sentences("text"), _lower_tokens).alias("sentences"))
    return cut.mapInArrow(run, "doc_id long, toxic int, score double")


def share(predicted: DataFrame, df: DataFrame) -> DataFrame:
    """corpus, n_docs, n_toxic, pct of documents found toxic."""
    met = df.select("doc_id", "corpus").join(predicted.select("doc_id", "toxic"), "doc_id")
    return met.groupBy("corpus").agg(F.count("*").alias("n_docs"), F.sum("toxic").cast("long").alias("n_toxic"), F.round(100 * F.sum("toxic") / F.count("*"), 6).alias("pct"))


def scores(predicted: DataFrame, labels: DataFrame) -> DataFrame:
    """Precision, recall and F1 beside the four counts."""
    q = quality(predicted.filter("toxic = 1"), labels)
    return q.withColumns({"precision": F.round(F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")), 6), "recall": F.round(F.try_divide(F.col("tp"), F.col("tp") + F.col("fn")), 6)}).withColumn("f1", F.round(F.try_divide(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")), 6))


def agreement(one: DataFrame, other: DataFrame) -> DataFrame:
    """in_one, in_other, n: how two detectors agree over documents (doc_id, toxic)."""
    both = one.select("doc_id", F.col("toxic").alias("in_one")).join(other.select("doc_id", F.col("toxic").alias("in_other")), "doc_id")
    return both.groupBy("in_one", "in_other").agg(F.count("*").alias("n"))
