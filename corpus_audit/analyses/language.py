"""Language shares, from given labels or a trained detector."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Profile length per language, what a gram outside a profile weighs, and the fold (id modulo FOLDS) that learning never sees.
SIZE, UNSEEN, FOLDS, HELD = 400, -12.0, 3, 1
_BITS = 21  # a code point


def share(df: DataFrame, label: str = "lang", drop_unknown: bool = False) -> DataFrame:
    """corpus, lang, n, share; a null label counts as UN."""
    slim = df.select("corpus", F.coalesce(label, F.lit("UN")).alias("lang"))
    counted = (slim.filter("lang <> 'UN'") if drop_unknown else slim).groupBy("corpus", "lang").agg(F.count("*").alias("n"))
    return counted.withColumn("share", F.round(F.col("n") / F.sum("n").over(W.partitionBy("corpus")), 6))


def held_out(key: str = "doc_id") -> Column:
    return F.coalesce(F.pmod(F.col(key), F.lit(FOLDS)) == HELD, F.lit(False))


def _letters(text: str = "text") -> Column:
    """Lower case, with one blank for each stretch of other characters than letters."""
    return F.regexp_replace(F.lower(F.coalesce(F.col(text), F.lit(""))), r"[^\p{L}]+", " ")


def _codes(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """The three-character codes of a batch's texts, and the row of each."""
    raw = [np.frombuffer(t.as_py().encode("utf-32-le", "surrogatepass"), dtype=np.uint32) for t in batch.column("letters")]
    size = np.asarray([max(0, len(x) - 2) for x in raw], dtype=np.int64)
    codes = [(x[:-2].astype(np.int64) << 2 * _BITS) | (x[1:-1].astype(np.int64) << _BITS) | x[2:] for x in raw if len(x) > 2]
    return np.concatenate([np.zeros(0, dtype=np.int64), *codes]), np.repeat(np.arange(len(raw)), size)


def profiles(df: DataFrame, size: int = SIZE) -> DataFrame:
    """lang, gram, weight: log shares of each language's most frequent character trigrams (a bounded table), from rows outside the held-out fold.

    Grams are counted in each task before they are shuffled, as numbers; ties go to the gram that sorts first.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes, row = _codes(batch)
            langs = batch.column("lang").to_numpy(zero_copy_only=False)
            for lang in sorted(set(langs)):
                found, n = np.unique(codes[(langs == lang)[row]], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(found), type=pa.string()), pa.array(found), pa.array(n)], names=["lang", "code", "c"])

    slim = df.filter(F.col("lang").isNotNull() & ~held_out()).select("lang", _letters().alias("letters"))
    counted = slim.mapInArrow(count, "lang string, code long, c long").groupBy("lang", "code").agg(F.sum("c").alias("c"))
    # Codes sort as the grams do: both go by code points.
    best = counted.withColumn("r", F.row_number().over(W.partitionBy("lang").orderBy(F.desc("c"), "code"))).filter(F.col("r") <= size)
    letter = [F.shiftright("code", 2 * _BITS), F.shiftright("code", _BITS), F.col("code")]
    gram = F.concat(*(F.decode(F.unhex(F.lpad(F.hex(x.bitwiseAND((1 << _BITS) - 1)), 8, "0")), "UTF-32") for x in letter))
    return best.select("lang", gram.alias("gram"), "code", F.log(F.col("c") / F.sum("c").over(W.partitionBy("lang"))).alias("weight"))


def detect(df: DataFrame, trained: DataFrame, margin: float = 0.0, key: str = "doc_id") -> DataFrame:
    """key, lang, score: the profile with the highest summed weight over the text's trigrams, above what unseen ones weigh.

    UN if no gram is in a profile or two are within ``margin``; ties go to the language that sorts first. The
    profiles are a table of languages times SIZE rows; every text is scored within its row.
    """
    rows = trained.select("lang", "code", "weight").collect()
    langs = sorted({r["lang"] for r in rows})
    known = np.asarray(sorted({r["code"] for r in rows}), dtype=np.int64)
    table = np.zeros((len(known) + 1, len(langs)))
    for r in rows:
        table[np.searchsorted(known, r["code"]), langs.index(r["lang"])] = r["weight"] - UNSEEN

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes, row = _codes(batch)
            at = np.searchsorted(known, codes)
            at[at < len(known)] = np.where(known[at[at < len(known)]] == codes[at < len(known)], at[at < len(known)], len(known))
            sums = np.stack([np.bincount(row, table[at, k], minlength=batch.num_rows) for k in range(len(langs))], axis=1) if langs else np.zeros((batch.num_rows, 0))
            sums = np.round(sums, 6)
            best = sums.argmax(axis=1) if langs else np.zeros(batch.num_rows, dtype=np.int64)
            top = np.sort(sums, axis=1)[:, ::-1]
            sure = (top[:, 0] > 0) & ((top[:, 0] - top[:, 1] > margin) if margin and len(langs) > 1 else True) if langs else np.zeros(batch.num_rows, dtype=bool)
            found = [langs[b] if ok else "UN" for b, ok in zip(best, sure, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(key), pa.array(found, type=pa.string()), pa.array(top[:, 0] if langs else np.zeros(batch.num_rows))], names=[key, "lang", "score"])

    return df.select(key, _letters().alias("letters")).mapInArrow(run, f"`{key}` {dict(df.dtypes)[key]}, lang string, score double")


def accuracy(detected: DataFrame, df: DataFrame) -> DataFrame:
    """lang, n, n_right, accuracy over the held-out fold, by the given language."""
    truth = df.filter(held_out() & F.col("lang").isNotNull()).select("doc_id", F.col("lang").alias("given"))
    met = truth.join(detected.select("doc_id", F.col("lang").alias("found")), "doc_id")
    right = F.count_if(F.col("given") == F.col("found"))
    return met.groupBy(F.col("given").alias("lang")).agg(F.count("*").alias("n"), right.alias("n_right"), F.round(right / F.count("*"), 6).alias("accuracy"))
