"""Hosts, schemes and public suffixes of URLs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpus_audit.text.tokenize import n_tokens

#: Share of HTTPS among visits to the web's sites that an outside survey gives.
HTTPS_REFERENCE = 0.95


def host(url: Column | str = "url") -> Column:
    """Lower-case host; null where the URL cannot be parsed."""
    return F.lower(F.try_parse_url(F.col(url) if isinstance(url, str) else url, F.lit("HOST")))


def shares(df: DataFrame, key: str, n: Column, k: int | None = None) -> DataFrame:
    """corpus, key, n, share of the corpus; with ``k`` only the k largest keys of each corpus."""
    counted = df.groupBy("corpus", key).agg(n.alias("n"))
    whole = W.partitionBy("corpus")
    out = counted.withColumn("share", F.round(F.col("n") / F.sum("n").over(whole), 6))
    if k is not None:
        out = out.withColumn("__r", F.row_number().over(whole.orderBy(F.desc("n"), key))).filter(F.col("__r") <= k).drop("__r")
    return out


def hosts(df: DataFrame, weight: str = "docs", k: int | None = 10) -> DataFrame:
    """The k largest hosts per corpus by documents or by tokens, among documents with a host."""
    slim = df.select("corpus", host().alias("host"), (n_tokens("text") if weight == "tokens" else F.lit(1).cast("long")).alias("w"))
    return shares(slim.filter(F.col("host").isNotNull()), "host", F.sum("w"), k)


def quantiles(df: DataFrame, qs: tuple[float, ...] = (0.01, 0.25, 0.5, 0.75, 0.99), exact: bool = True) -> DataFrame:
    """Quantiles over hosts of the tokens that a host has, and the number of hosts, per corpus."""
    totals = df.select("corpus", host().alias("host"), n_tokens("text").alias("t")).filter(F.col("host").isNotNull()).groupBy("corpus", "host").agg(F.sum("t").alias("t"))
    cut = (lambda q: F.percentile("t", q)) if exact else (lambda q: F.percentile_approx("t", q, 10_000).cast("double"))
    return totals.groupBy("corpus").agg(*(F.round(cut(q), 6).alias(f"q{round(100 * q):02d}") for q in qs), F.count("*").alias("n_hosts"))


def schemes(df: DataFrame) -> DataFrame:
    slim = df.select("corpus", F.lower(F.try_parse_url("url", F.lit("PROTOCOL"))).alias("scheme"))
    return shares(slim.filter(F.col("scheme").isNotNull()), "scheme", F.count("*"))


def suffix(host_name: Column, known: list[str]) -> Column:
    """The longest known public suffix of a host, else its last label. The list is part of the plan, not a join."""
    cases = F.lit(None).cast("string")
    for s in sorted(known, key=lambda s: (s.count("."), s)):  # later ones are longer and win
        cases = F.when((host_name == s) | host_name.endswith("." + s), F.lit(s)).otherwise(cases)
    return F.coalesce(cases, F.substring_index(host_name, ".", -1))


def suffixes(df: DataFrame, known: list[str], k: int | None = 10) -> DataFrame:
    slim = df.select("corpus", suffix(host(), known).alias("suffix"))
    return shares(slim.filter(F.col("suffix").isNotNull()), "suffix", F.count("*"), k)


def suffixes_by_table(df: DataFrame, table: DataFrame, k: int | None = 10) -> DataFrame:
    """As ``suffixes`` for a long list in a table: each host tries its label tails in one equi join."""
    hosts_only = df.select("corpus", host().alias("host")).filter(F.col("host").isNotNull()).groupBy("corpus", "host").agg(F.count("*").alias("w"))
    tried = hosts_only.select("corpus", "host", "w", F.posexplode(F.split("host", r"\.")).alias("i", "label"))
    tried = tried.withColumn("tail", F.expr("substring_index(host, '.', -(i + 1))"))
    best = tried.join(table.select(F.col("suffix").alias("tail")).distinct(), "tail").groupBy("corpus", "host").agg(F.max_by("tail", F.length("tail")).alias("suffix"))
    named = hosts_only.join(best, ["corpus", "host"], "left").withColumn("suffix", F.coalesce("suffix", F.substring_index("host", ".", -1)))
    return shares(named, "suffix", F.sum("w"), k)
