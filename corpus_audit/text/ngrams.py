"""n-grams inside one document, as strings or as 64-bit hashes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpus_audit.text.tokenize import tokens

#: Longest token stretch handled as one row.
CHUNK_TOKENS = 100_000


def windows(array: Column | str, n: int) -> Column:
    """Array of the n-token windows; shorter documents give none. ``array`` must be a stored column."""
    array = F.col(array) if isinstance(array, str) else array
    starts = F.sequence(F.lit(1), F.size(array) - (n - 1))
    return F.when(F.size(array) >= n, F.transform(starts, lambda i: F.slice(array, i, n))).otherwise(F.array().cast("array<array<string>>"))


def chunked(df: DataFrame, n: int, array: str = "tokens", size: int = CHUNK_TOKENS) -> DataFrame:
    """Cut token arrays into stretches of ``size`` that overlap by n - 1, which leaves the multiset of n-grams as it is."""
    last = F.greatest(F.lit(0), F.floor((F.size(array) - n) / size)).cast("int")
    pieces = F.transform(F.sequence(F.lit(0), last), lambda k: F.slice(array, k * size + 1, F.lit(size + n - 1)))
    return df.select(*(c for c in df.columns if c != array), F.explode(pieces).alias(array))


def grams(df: DataFrame, n: int, text: str = "text", keep: list[str] | None = None, sep: str = " ", mode: str = "unicode") -> DataFrame:
    """One row per n-gram: ``keep`` columns and ``gram``."""
    keep = keep or []
    tokenized = df.select(*keep, tokens(text, mode).alias("tokens"))
    if n == 1:
        return tokenized.select(*keep, F.explode("tokens").alias("gram"))
    cut = chunked(tokenized, n)
    return cut.select(*keep, F.explode(windows("tokens", n)).alias("window")).select(*keep, F.array_join("window", sep).alias("gram"))


def window_rows(df: DataFrame, n: int, keep: list[str] | None = None, text: str = "text", mode: str = "unicode") -> DataFrame:
    """As ``grams`` with ``window``, the tokens as an array, in place of the string (one token stays a string)."""
    keep = keep or []
    tokenized = df.select(*keep, tokens(text, mode).alias("tokens"))
    if n == 1:
        return tokenized.select(*keep, F.explode("tokens").alias("window"))
    return chunked(tokenized, n).select(*keep, F.explode(windows("tokens", n)).alias("window"))


def grams_sql(n: int, source: str = "documents", keep: str = "doc_id, source AS corpus", column: str = "text") -> str:
    """A DuckDB subquery with the same rows."""
    from corpus_audit.text.tokenize import tokens_sql

    names = ", ".join(x.split(" AS ")[-1].strip() for x in keep.split(","))
    inner = f"SELECT {keep}, {tokens_sql(column)} AS w FROM {source}"
    if n == 1:
        return f"(SELECT {names}, unnest(w) AS gram FROM ({inner}))"
    return f"(SELECT {names}, array_to_string(list_slice(w, i, i + {n - 1}), ' ') AS gram FROM (SELECT {names}, w, unnest(range(1, len(w) - {n - 2})) AS i FROM ({inner}) WHERE len(w) >= {n}))"
