"""Evaluation items whose fields all occur in one document.

Both routes agree with a search of every field in every text. The index route looks up one
shingle of three tokens per field and verifies the few candidates. The shingle is taken from between the field's first and
last white space: there tokens are cut alike inside and outside the field, while a word at either end may go on
in the text. Fields too short for one go by the scan route, which passes automata of their strings over
the texts, a bounded number of fields each.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpus_audit.text.ngrams import windows
from corpus_audit.text.tokenize import tokens

SENTENCE = r"[^.!?]+[.!?]*"
ANCHOR = 3
#: Fields that one automaton holds, about.
MAX_FIELDS = 100_000
#: What lies between the first and the last white space of a field.
INNER = r"(?s)[\s\p{Z}\x0B](.*)[\s\p{Z}\x0B]"


def items_from_text(table: DataFrame, item: str = "item_id", text: str = "text") -> DataFrame:
    """item_id, fields: the sentences of a text as an item's input fields."""
    parts = F.transform(F.regexp_extract_all(F.col(text), F.lit(SENTENCE), F.lit(0)), lambda s: F.trim(s))
    return table.select(F.col(item).alias("item_id"), F.filter(parts, lambda s: s != "").alias("fields"))


def eligible(items: DataFrame, least: int = 2) -> DataFrame:
    """Items with at least ``least`` input fields."""
    return items.filter(F.size("fields") >= least)


def _fields(items: DataFrame) -> DataFrame:
    return items.select("item_id", F.posexplode("fields").alias("field", "value"))


def hits_by_scan(docs: DataFrame, fields: DataFrame) -> DataFrame:
    """doc_id, item_id, field by one pass of an Aho-Corasick automaton over each text; more than MAX_FIELDS fields are dealt to several by their hash."""
    blocks = -(-fields.count() // MAX_FIELDS)
    out = _scan(docs, fields if blocks <= 1 else fields.filter(F.pmod(F.xxhash64("item_id", "field"), F.lit(blocks)) == 0))
    for k in range(1, blocks):
        out = out.union(_scan(docs, fields.filter(F.pmod(F.xxhash64("item_id", "field"), F.lit(blocks)) == k)))
    return out


def _scan(docs: DataFrame, fields: DataFrame) -> DataFrame:
    rows = [(r["item_id"], r["field"], r["value"]) for r in fields.select("item_id", "field", "value").collect()]

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import ahocorasick

        owners: dict[str, list] = {}
        for item, field, value in rows:
            owners.setdefault(value, []).append((item, field))
        machine = ahocorasick.Automaton()
        for value, own in owners.items():
            machine.add_word(value, own)
        if owners:
            machine.make_automaton()
        for batch in batches:
            found = [(d, *o) for d, t in zip(batch["doc_id"], batch["text"], strict=True) for o in ({o for _, own in machine.iter(t) for o in own} if owners and t else ())]
            yield pd.DataFrame(found, columns=["doc_id", "item_id", "field"])

    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).mapInPandas(scan, "doc_id long, item_id long, field int")


def hits_by_index(docs: DataFrame, fields: DataFrame) -> DataFrame:
    """doc_id, item_id, field by anchor shingles, then by the field's string in the text."""
    cut = fields.withColumn("inner", tokens(F.regexp_extract("value", INNER, 1)))
    anchored = cut.filter(F.size("inner") >= ANCHOR)
    middle = F.floor((F.size("inner") - ANCHOR) / 2).cast("int") + 1
    anchors = anchored.select("item_id", "field", "value", F.xxhash64(F.slice("inner", middle, F.lit(ANCHOR))).alias("anchor"))
    shingled = docs.select("doc_id", tokens("text").alias("tokens")).select("doc_id", F.explode(F.array_distinct(F.transform(windows("tokens", ANCHOR), lambda w: F.xxhash64(w)))).alias("anchor"))
    met = shingled.join(anchors, "anchor").select("doc_id", "item_id", "field", "value")
    verified = met.join(docs.select("doc_id", "text"), "doc_id").filter(F.contains("text", "value")).select("doc_id", "item_id", "field")
    short = cut.filter(F.size("inner") < ANCHOR).select("item_id", "field", "value")
    return verified.union(hits_by_scan(docs, short)).distinct()


def evaluate(docs: DataFrame, items: DataFrame, method: str = "scan", require: str = "all") -> DataFrame:
    """doc_id, item_id: documents that hold all (any) fields of an item, in any order."""
    hits = (hits_by_scan if method == "scan" else hits_by_index)(docs, _fields(items))
    counted = hits.groupBy("doc_id", "item_id").agg(F.countDistinct("field").alias("n"))
    if require == "any":
        return counted.select("doc_id", "item_id")
    return counted.join(items.select("item_id", F.size("fields").alias("n_fields")), "item_id").filter("n = n_fields").select("doc_id", "item_id")


def per_item(pairs: DataFrame, items: DataFrame) -> DataFrame:
    """item_id, n_fields, n_docs, also for items that occur nowhere."""
    counted = pairs.groupBy("item_id").agg(F.countDistinct("doc_id").alias("n_docs"))
    return items.select("item_id", F.size("fields").cast("long").alias("n_fields")).join(counted, "item_id", "left").select("item_id", "n_fields", F.coalesce("n_docs", F.lit(0)).alias("n_docs"))


def rate(pairs: DataFrame, docs: DataFrame, items: DataFrame) -> DataFrame:
    """corpus, n_items, n_hit, rate: the share of items found in each corpus."""
    hit = pairs.join(docs.select("doc_id", "corpus"), "doc_id").groupBy("corpus").agg(F.countDistinct("item_id").alias("n_hit"))
    total = items.agg(F.count("*").alias("n_items"))
    everywhere = docs.select("corpus").distinct().join(hit, "corpus", "left").join(F.broadcast(total))
    n_hit = F.coalesce("n_hit", F.lit(0))
    return everywhere.select("corpus", "n_items", n_hit.alias("n_hit"), F.round(n_hit / F.col("n_items"), 6).alias("rate"))


def report(rates: DataFrame, threshold: float = 0.05) -> DataFrame:
    """set, max_rate, above_threshold, is_zero over ``rates(set, corpus, rate)``."""
    top = F.max("rate")
    return rates.groupBy("set").agg(top.alias("max_rate"), (top >= threshold).alias("above_threshold"), (top == 0).alias("is_zero"))


def remove(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """Documents that hold no item."""
    return docs.join(pairs.select("doc_id").distinct(), "doc_id", "left_anti")


def overlap(docs: DataFrame, items: DataFrame, n: int = 8, share: float = 0.5) -> DataFrame:
    """doc_id, item_id, overlap: documents that hold at least ``share`` of an item's distinct n-token shingles (also paraphrases)."""
    whole = items.select("item_id", tokens(F.array_join("fields", " ")).alias("tokens")).select("item_id", F.array_distinct(F.transform(windows("tokens", n), lambda w: F.xxhash64(w))).alias("s"))
    wanted = whole.select("item_id", F.size("s").alias("n_shingles"), F.explode("s").alias("h"))
    have = docs.select("doc_id", tokens("text").alias("tokens")).select("doc_id", F.explode(F.array_distinct(F.transform(windows("tokens", n), lambda w: F.xxhash64(w)))).alias("h"))
    met = have.join(wanted, "h").groupBy("doc_id", "item_id", "n_shingles").agg(F.count("*").alias("n"))
    return met.withColumn("overlap", F.round(F.col("n") / F.col("n_shingles"), 6)).filter(F.col("overlap") >= share).select("doc_id", "item_id", "overlap")
