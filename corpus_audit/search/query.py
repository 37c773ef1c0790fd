"""Queries over postings: frequencies, Boolean expressions, phrases, retrieval."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Term:
    text: str


@dataclass(frozen=True)
class Phrase:
    terms: tuple[str, ...]


@dataclass(frozen=True)
class And:
    parts: tuple


@dataclass(frozen=True)
class Or:
    parts: tuple


@dataclass(frozen=True)
class Not:
    part: object


def _positions(index: DataFrame, term: str, shift: int = 0) -> DataFrame:
    """doc_id, at: occurrences of a term, moved back by its place in a phrase."""
    return index.filter(F.col("term") == term).select("doc_id", F.explode("positions").alias("p")).select("doc_id", (F.col("p") - shift).alias("at"))


def phrase_starts(index: DataFrame, terms: list[str] | tuple[str, ...]) -> DataFrame:
    """doc_id, at of each occurrence of the terms in a row: semi joins on (doc_id, place), no text is read."""
    parts = [_positions(index, t, k) for k, t in enumerate(terms)]
    return reduce(lambda a, b: a.join(b, ["doc_id", "at"], "left_semi"), parts)


def frequency(index: DataFrame, phrases: list[list[str]]) -> DataFrame:
    """phrase, df, tf: documents with the phrase and its occurrences (also 0); one-term phrases read counts alone."""
    def one(terms: list[str]) -> DataFrame:
        name = F.lit(" ".join(terms)).alias("phrase")
        if len(terms) == 1:
            hits = index.filter(F.col("term") == terms[0])
            return hits.agg(F.countDistinct("doc_id").alias("df"), F.coalesce(F.sum("tf"), F.lit(0)).alias("tf")).select(name, "df", "tf")
        return phrase_starts(index, terms).agg(F.countDistinct("doc_id").alias("df"), F.count("*").alias("tf")).select(name, "df", "tf")

    return reduce(DataFrame.unionByName, [one(t) for t in phrases])


def ngram_counts(index: DataFrame, gram: str, sep: str = " ") -> DataFrame:
    return frequency(index, [gram.split(sep)]).withColumnRenamed("phrase", "gram")


def run(index: DataFrame, expr: object) -> DataFrame:
    """doc_id of the documents that satisfy an expression; ``Not`` is relative to the indexed documents."""
    match expr:
        case Term(text):
            return index.filter(F.col("term") == text).select("doc_id").distinct()
        case Phrase(terms):
            return phrase_starts(index, terms).select("doc_id").distinct()
        case And(parts):
            kept = [p for p in parts if not isinstance(p, Not)]
            out = reduce(lambda a, b: a.join(b, "doc_id", "left_semi"), [run(index, p) for p in kept]) if kept else index.select("doc_id").distinct()
            return reduce(lambda a, p: a.join(run(index, p.part), "doc_id", "left_anti"), [p for p in parts if isinstance(p, Not)], out)
        case Or(parts):
            return reduce(DataFrame.union, [run(index, p) for p in parts]).distinct()
        case Not(part):
            return index.select("doc_id").distinct().join(run(index, part), "doc_id", "left_anti")
    raise TypeError(f"not a query: {expr!r}")


def fetch(hits: DataFrame, docs: DataFrame, k: int | None = None) -> DataFrame:
    """The documents of the hits, the k smallest ids if k is given."""
    hits = hits.select("doc_id").distinct()
    if k is not None:
        hits = F.broadcast(hits.orderBy("doc_id").limit(k))
    return docs.join(hits, "doc_id", "left_semi")
