"""E-mail addresses, phone numbers and IP addresses by rules."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: The three patterns. The captured group, if any, is the value.
EMAIL = r"[.\s@,?!;:)(]*([^\s@]+@[^\s@,?!;:)(]+?)[.\s@,?!;:)(]?[\s\n\r]"
EMAIL_AT_END = r"[.\s@,?!;:)(]*([^\s@]+@[^\s@,?!;:)(]+?)[.\s@,?!;:)(]?(?:[\s\n\r]|$)"
PHONE = r"\s+\(?\d{3}\)?[-. ]*\d{3}[-. ]?\d{4}"
PHONE_CLOSED = r"\s+\(?\d{3}\)?[-. ]*\d{3}[-. ]?\d{4}\b"
PHONE_FREE_AREA = r"\s+(?:\(?\d{3}\)?)?[-. ]*\d{3}[-. ]?\d{4}"
_OCTET = r"(?:25[0-5]|2[0-4][0-9]|[01]?[0-9][0-9]?)"
IP = rf"(?:{_OCTET}\.){{3}}{_OCTET}"
URL = r"[A-Za-z]+://[^\s]+"
#: Characters around a phone number or address in which ISBN, DOI or # rules it out.
CONTEXT = 50
#: A strict reading of each kind, the judge of precision on these data.
STRICT = {"email": r"^[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}$", "phone": r"^\(?\d{3}\)?[-. ]\d{3}[-. ]\d{4}$", "ip": r"^\d+\.\d+\.\d+\.\d+$"}
KINDS = ("email", "phone", "ip")


def prefilter(df: DataFrame, max_run: int = 50) -> DataFrame:
    """Drop texts in which a mark repeats more than ``max_run`` times in a row; such runs slow the patterns down."""
    marks = r"(?:" + "|".join(rf"\{c}{{{max_run + 1},}}" for c in "!#$%&*+-./:;<=>?@^_~()") + ")"
    return df.filter(~F.coalesce(F.col("text").rlike(marks), F.lit(False)))


def _context_free(text: Column, value: Column) -> Column:
    """No ISBN, DOI or # within CONTEXT characters of the value's first place in the text."""
    at = F.instr(text, value)
    near = F.substr(text, F.greatest(F.lit(1), at - CONTEXT), F.length(value) + CONTEXT + F.least(F.lit(CONTEXT), at - 1))
    return ~near.rlike("(?i)isbn|doi") & ~F.contains(near, F.lit("#"))


def values(kind: str, boundary: str = "open", at_end: bool = False, area: str = "required") -> Column:
    """Array of the values of a kind in ``text`` that pass the kind's rules, repeats included."""
    text = F.coalesce("text", F.lit(""))
    if kind == "email":
        found = F.regexp_extract_all(text, F.lit(EMAIL_AT_END if at_end else EMAIL), F.lit(1))
        return F.filter(found, lambda v: (F.substring_index(v, "@", 1) != "(") & F.contains(F.substring_index(v, "@", -1), F.lit(".")))
    if kind == "ip":
        return F.filter(F.regexp_extract_all(text, F.lit(IP), F.lit(0)), lambda v: _context_free(text, v))
    pattern = PHONE_FREE_AREA if area == "optional" else PHONE_CLOSED if boundary == "closed" else PHONE
    found = F.transform(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda v: F.regexp_replace(v, r"^\s+", ""))
    urls = F.array_join(F.regexp_extract_all(text, F.lit(URL), F.lit(0)), " ")
    return F.filter(found, lambda v: _context_free(text, v) & ~F.contains(urls, v))


def find(df: DataFrame, kind: str, **options) -> DataFrame:
    """doc_id, corpus, kind, value: one row per match. Cheap tests for a mark or digit stand before the patterns."""
    guard = F.contains("text", F.lit("@")) if kind == "email" else F.col("text").rlike("[0-9]")
    return df.filter(guard).select("doc_id", "corpus", F.lit(kind).alias("kind"), F.explode(values(kind, **options)).alias("value"))


def find_all(df: DataFrame, kinds: tuple[str, ...] = KINDS, **options) -> DataFrame:
    out = find(df, kinds[0], **options)
    for kind in kinds[1:]:
        out = out.union(find(df, kind, **options))
    return out


def counts(df: DataFrame) -> DataFrame:
    """corpus, kind, n."""
    return find_all(df).groupBy("corpus", "kind").agg(F.count("*").alias("n"))


def sample_for_review(found: DataFrame, size: int = 100, seed: str = "p") -> DataFrame:
    """Up to ``size`` matches per corpus and kind in a seeded order, for judging."""
    key = F.md5(F.concat(F.lit(seed), F.col("doc_id").cast("string"), F.lit(":"), F.col("value")).cast("binary"))
    order = W.partitionBy("corpus", "kind").orderBy(key, "doc_id", "value")
    return found.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= size).drop("r")


def judge(found: DataFrame) -> DataFrame:
    """``found`` with is_true by the strict reading."""
    strict = F.lit(False)
    for kind, pattern in STRICT.items():
        strict = F.when(F.col("kind") == kind, F.col("value").rlike(pattern)).otherwise(strict)
    return found.withColumn("is_true", strict)


def precision(judged: DataFrame) -> DataFrame:
    """corpus, kind, n, precision."""
    return judged.groupBy("corpus", "kind").agg(F.count("*").alias("n"), F.round(F.avg(F.col("is_true").cast("double")), 6).alias("precision"))


def extrapolate(raw: DataFrame, judged: DataFrame) -> DataFrame:
    """corpus, kind, est: matches times precision."""
    return raw.join(judged.select("corpus", "kind", "precision"), ["corpus", "kind"]).select("corpus", "kind", F.round(F.col("n") * F.col("precision"), 6).alias("est"))


def rate(estimated: DataFrame, summary: DataFrame) -> DataFrame:
    """corpus, kind, rate per token; joined on the corpus, so rows cannot shift."""
    return estimated.join(summary.select("corpus", "n_tokens"), "corpus").select("corpus", "kind", F.round(F.col("est") / F.col("n_tokens"), 9).alias("rate"))


def recall(planted: DataFrame, found: DataFrame) -> DataFrame:
    """corpus, n_planted, n_found, recall of known values (doc_id, corpus, value) among the found ones."""
    hit = planted.join(found.select("doc_id", "value").distinct().withColumn("hit", F.lit(1)), ["doc_id", "value"], "left")
    return hit.groupBy("corpus").agg(F.count("*").alias("n_planted"), F.count("hit").alias("n_found"), F.round(F.count("hit") / F.count("*"), 6).alias("recall"))
