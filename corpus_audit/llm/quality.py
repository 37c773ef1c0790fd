"""Host-level quality rules, all in DataFrame expressions.

Each document is held against fixed rules. A host's failure rate is shrunk by a beta prior that is
fitted to all hosts by the method of moments, with the binomial noise of their counts taken off. A
host falls, with all its documents, if its posterior lies above the limit for sure: its mean less ``SURE``
standard deviations. The limit is a multiple of the mean rate of all documents and ``HOST_LIMIT`` at least, so a
few bad documents do not condemn a small host, nor a corpus that fails often all its hosts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.llm.common import materialize, small_side, whole_text

MIN_WORDS, MAX_REPEAT_PERCENT, WINDOW = 20, 30, 8
#: Further document rules; they count toward the host's rate alone.
MAX_SYMBOL_PERCENT, MAX_DUP_LINE_PERCENT = 10, 50
#: The limit of a host's failure rate: HOST_LIMIT, or HOST_MULTIPLE times the rate of all documents up to MAX_HOST_LIMIT.
HOST_LIMIT, HOST_MULTIPLE, MAX_HOST_LIMIT = 0.35, 2.0, 0.9
#: Standard deviations by which a host's posterior mean must lie above the limit.
SURE = 1.645
#: Prior strength where hosts are too few to fit one, and the range it is held to.
PRIOR_STRENGTH, MIN_STRENGTH, MAX_STRENGTH = 10.0, 2.0, 1000.0
SPACES, SYMBOLS = " \t\n\x0b\x0c\r", "#*$%&|<>"


def _without(text: Column, chars: str) -> Column:
    return F.translate(text, chars, "")


def measures(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """``keep`` and n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words, base_failed.

    Null texts are empty. Words are runs of bytes other than space and 0x09 to 0x0D. Every array
    below is a column of its own because it is read twice: an expression read once would be pulled
    into the lambda that reads it and evaluated anew for each element.
    """
    t = F.col("__text")
    spaced = F.translate(t, SPACES[1:], " " * 5)
    df = docs.select(*keep, whole_text(text).alias("__text"))
    df = df.select(
        *keep,
        F.filter(F.split(spaced, " "), lambda w: w != "").alias("__words"),
        F.length(_without(t, SPACES)).cast("long").alias("word_chars"),
        (F.length(t) - F.length(_without(t, SYMBOLS))).cast("long").alias("n_symbols"),
        F.filter(F.split(t, "\n"), lambda x: F.length(_without(x, SPACES)) > 0).alias("__lines"),
    )
    df = df.select(
        *keep, "word_chars", "n_symbols",
        F.size("__words").cast("long").alias("n_words"),
        F.transform("__words", lambda w: F.xxhash64(w)).alias("__hashes"),
        F.size("__lines").cast("long").alias("n_lines"),
        (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long").alias("n_dup_lines"),
    )
    some = F.size("__hashes") >= WINDOW
    windows = F.transform(F.sequence(F.lit(1), F.size("__hashes") - (WINDOW - 1)), lambda i: F.xxhash64(F.slice("__hashes", i, WINDOW)))
    kept = [*keep, "word_chars", "n_symbols", "n_words", "n_lines", "n_dup_lines"]
    df = df.select(*kept, F.when(some, windows).otherwise(F.array().cast("array<bigint>")).alias("__windows"))
    # Only a text in which some window recurs needs the sort that finds where.
    recurs = F.size(F.array_distinct("__windows")) < F.size("__windows")
    placed = F.array_sort(F.transform("__windows", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    df = df.select(*kept, F.when(recurs, placed).alias("__placed"))
    size = F.size("__placed")
    pairs = F.zip_with(F.slice("__placed", 1, size - 1), F.slice("__placed", 2, size - 1), lambda a, b: F.when(a["h"] == b["h"], F.array(a["i"], b["i"])).otherwise(F.array().cast("array<int>")))
    df = df.select(*kept, F.when(F.col("__placed").isNotNull(), F.array_sort(F.array_distinct(F.flatten(pairs)))).alias("__at"))
    size = F.size("__at")
    steps = F.zip_with(F.slice("__at", 1, size - 1), F.slice("__at", 2, size - 1), lambda a, b: F.least(F.lit(WINDOW), b - a))
    covered = F.when(F.col("__at").isNotNull(), F.aggregate(steps, F.lit(WINDOW), lambda s, x: s + x)).otherwise(F.lit(0))
    df = df.select(*kept, covered.cast("long").alias("n_repeat_words"))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    return df.withColumn("base_failed", failed)


def rule_failed() -> Column:
    """The failure that counts toward the host: a base rule, too many symbols, or too many repeated lines."""
    return F.col("base_failed") | (100 * F.col("n_symbols") > MAX_SYMBOL_PERCENT * F.col("word_chars")) | (100 * F.col("n_dup_lines") > MAX_DUP_LINE_PERCENT * F.col("n_lines"))


def host_verdicts(measured: DataFrame, host: str = "source") -> DataFrame:
    """``host_key, host_docs, host_failed, host_rate, host_limit, host_kept``, one row per host (null is a host of its own).

    With n and f the documents and failures of a host, m their mean rate and S = sum n (f/n - m)^2, the spread of hosts
    beyond binomial noise is rho = (S / (m (1 - m)) - (k - 1)) / (N - sum n^2 / N - (k - 1)) for k hosts and N documents, and the
    prior's strength 1 / rho - 1, held to [MIN_STRENGTH, MAX_STRENGTH]; no spread gives the strongest. Where m is 0
    or 1, or there are too few hosts, it is PRIOR_STRENGTH.
    """
    hosts = measured.groupBy(F.col(host).alias("host_key")).agg(F.count("*").alias("host_docs"), F.sum(rule_failed().cast("long")).alias("host_failed"))
    n, f = F.col("host_docs").cast("double"), F.col("host_failed").cast("double")
    sums = hosts.agg(F.count("*").alias("k"), F.sum(n).alias("n"), F.sum(f).alias("f"), F.sum(n * n).alias("nn"), F.sum(f * f / n).alias("ff"))
    m = F.col("f") / F.col("n")
    noise = m * (1 - m)
    free = F.col("n") - F.col("nn") / F.col("n") - (F.col("k") - 1)
    rho = ((F.col("ff") - m * F.col("f")) / noise - (F.col("k") - 1)) / free
    held = F.when(rho > 0, F.least(F.lit(MAX_STRENGTH), F.greatest(F.lit(MIN_STRENGTH), 1 / F.when(rho > 0, rho) - 1))).otherwise(F.lit(MAX_STRENGTH))
    strength = F.when((noise > 0) & (free > 0), held).otherwise(F.lit(PRIOR_STRENGTH))
    limit = F.greatest(F.lit(HOST_LIMIT), F.least(F.lit(MAX_HOST_LIMIT), F.lit(HOST_MULTIPLE) * m))
    prior = sums.filter("k > 0").select(m.alias("m"), strength.alias("strength"), F.round(limit, 6).alias("host_limit"))
    shrunk = (F.col("host_failed") + F.col("m") * F.col("strength")) / (F.col("host_docs") + F.col("strength"))
    # The prior is one row, an aggregate without keys.
    rated = hosts.join(F.broadcast(prior)).withColumn("rate", shrunk).withColumn("low", F.col("rate") - SURE * F.sqrt(F.greatest(F.lit(0.0), F.col("rate") * (1 - F.col("rate"))) / (F.col("host_docs") + F.col("strength") + 1)))
    return rated.select("host_key", "host_docs", "host_failed", F.round("rate", 6).alias("host_rate"), "host_limit", (F.round("low", 6) <= F.col("host_limit")).alias("host_kept"))


def judged(measured: DataFrame, host: str = "source") -> DataFrame:
    """``measured`` (a stored table) with its host's verdict and ``kept``: no base rule failed and the host is kept."""
    verdicts = small_side(host_verdicts(measured, host))
    joined = measured.join(verdicts, measured[host].eqNullSafe(verdicts["host_key"]))
    return joined.withColumn("kept", ~F.col("base_failed") & F.col("host_kept"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measures, base rules and verdict of every document, with its host's counts.

    Null and empty texts have no words and fail; texts of any length are read whole; repeated rows are judged and
    counted as often as they come; a null source is a host of its own; an empty table gives an empty
    result; columns other than doc_id, source and text are not read. Rates and limits are rounded before they are
    compared, and a host on the limit stays.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    base = materialize(measures(docs, ["doc_id", "source"]), "quality")
    return judged(base).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.col("source").alias("host"), "host_docs", "host_failed", "host_rate", "host_limit", "host_kept")


OP7_SQL = rf"""
WITH w AS (
  SELECT doc_id, source, coalesce(text, '') AS t,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines
  FROM documents),
g AS (
  SELECT doc_id, i, md5(array_to_string(list_slice(words, i, i + {WINDOW - 1}), ' ')) AS h
  FROM (SELECT doc_id, words, unnest(range(1, len(words) - {WINDOW - 2})) AS i FROM w WHERE len(words) >= {WINDOW})),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, h) AS c FROM g) WHERE c > 1),
c AS (
  SELECT doc_id, sum(least({WINDOW}, coalesce(nxt - i, {WINDOW}))) AS n_repeat_words
  FROM (SELECT doc_id, i, lead(i) OVER (PARTITION BY doc_id ORDER BY i) AS nxt FROM r) GROUP BY doc_id),
m AS (
  SELECT w.doc_id, source, CAST(len(words) AS BIGINT) AS n_words,
         CAST(coalesce(list_sum(list_transform(words, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
         CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
         CAST(len(lines) AS BIGINT) AS n_lines, CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
         CAST(coalesce(c.n_repeat_words, 0) AS BIGINT) AS n_repeat_words
  FROM w LEFT JOIN c ON w.doc_id = c.doc_id),
b AS (SELECT *, (n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words) AS base_failed FROM m),
f AS (SELECT *, (base_failed OR 100 * n_symbols > {MAX_SYMBOL_PERCENT} * word_chars OR 100 * n_dup_lines > {MAX_DUP_LINE_PERCENT} * n_lines) AS failed FROM b),
h AS (SELECT source, count(*) AS host_docs, CAST(sum(CAST(failed AS BIGINT)) AS BIGINT) AS host_failed FROM f GROUP BY source),
a AS (
  SELECT count(*) AS k, sum(CAST(host_docs AS DOUBLE)) AS n, sum(CAST(host_failed AS DOUBLE)) AS fails,
         sum(CAST(host_docs AS DOUBLE) * host_docs) AS nn, sum(CAST(host_failed AS DOUBLE) * host_failed / host_docs) AS ff FROM h),
q AS (SELECT fails / n AS m, CASE WHEN fails > 0 AND fails < n AND n - nn / n - (k - 1) > 0 THEN ((ff - fails * fails / n) / (fails / n * (1 - fails / n)) - (k - 1)) / (n - nn / n - (k - 1)) END AS rho FROM a),
p AS (
  SELECT m, CASE WHEN rho IS NULL THEN {PRIOR_STRENGTH} WHEN rho > 0 THEN least({MAX_STRENGTH}, greatest({MIN_STRENGTH}, 1 / rho - 1)) ELSE {MAX_STRENGTH} END AS s,
         round(greatest({HOST_LIMIT}, least({MAX_HOST_LIMIT}, {HOST_MULTIPLE} * m)), 6) AS host_limit FROM q),
u AS (SELECT source, host_docs, host_failed, host_limit, s, (host_failed + m * s) / (host_docs + s) AS rate FROM h, p),
v AS (SELECT *, round(rate, 6) AS host_rate, round(rate - {SURE} * sqrt(greatest(0.0, rate * (1 - rate)) / (host_docs + s + 1)), 6) <= host_limit AS host_kept FROM u)
SELECT f.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       (NOT base_failed AND host_kept) AS kept, f.source AS host, host_docs, host_failed, host_rate, host_limit, host_kept
FROM f JOIN v ON f.source IS NOT DISTINCT FROM v.source
"""


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that pass: rows are stored once with their measures and joined to the host verdicts.

    A null text has no words and fails; an empty table stays empty; other columns are carried along untouched.
    """
    packed = docs.select(F.struct(*docs.columns).alias("__row"), F.col("source").alias("__host"), "text")
    base = materialize(measures(packed, ["__row", "__host"]), "quality")
    verdicts = small_side(host_verdicts(base, "__host"))
    kept = base.filter(~F.col("base_failed")).join(verdicts, base["__host"].eqNullSafe(verdicts["host_key"])).filter("host_kept")
    return kept.select("__row.*")
