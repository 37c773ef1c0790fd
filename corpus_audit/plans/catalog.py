"""Every query by name, with the DuckDB SQL that gives the same rows where SQL can.

Shared rules: top-k answers have a total order (count, then key), doubles are rounded, arrays are
joined to strings. Hashed queries use the md5 prefix here, which SQL has too; in production
``xxhash64`` is the default.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.analyses import contamination, curate, dates, distribution, domains, duplicates, geo, language, lengths, ngrams, overlap, pii, sentiment, stats, toxicity
from corpus_audit.counting import accuracy
from corpus_audit.counting.hashed import HashSpec, cell_counts, occupancy
from corpus_audit.functions import lexicons
from corpus_audit.operators import sketches
from corpus_audit.search import index, query
from corpus_audit.sources.io import documents, pages, spread, table
from corpus_audit.text.html import visible_text_sql
from corpus_audit.text.ngrams import grams, grams_sql
from corpus_audit.text.tokenize import n_tokens, tokens_sql

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
SPEC = HashSpec(m=65_536, fn="md5_prefix")
K = 10


def register(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _local(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return F.broadcast(spark.createDataFrame(rows, schema))


def texts(spark: SparkSession, sf: str) -> DataFrame:
    """Documents for analyses that do much work per text: a few splits are dealt over all cores."""
    return spread(documents(spark, sf))


def _by_lang(spark: SparkSession, sf: str) -> DataFrame:
    """Documents with the language as corpus."""
    return texts(spark, sf).withColumn("corpus", F.col("lang"))


def _values(rows: list[tuple], *names: str) -> str:
    quoted = ["(" + ", ".join(f"'{x}'" if isinstance(x, str) else repr(x) for x in r) + ")" for r in rows]
    return f"(SELECT * FROM (VALUES {', '.join(quoted)}) AS v({', '.join(names)}))"


# --- SQL fragments -------------------------------------------------------------------------
TOK = tokens_sql("text")
DOCS = f"(SELECT doc_id, source AS corpus, lang, coalesce(text, '') AS text, CAST(len({TOK}) AS BIGINT) AS n_tokens FROM documents)"
BLANK = r"regexp_replace(text, '[\s\p{Z}\x0B]+', '', 'g') = ''"
PAGES = f"(SELECT page_id AS doc_id, 'p' || CAST(page_id % 5 AS VARCHAR) AS corpus, url, {visible_text_sql('html')} AS text FROM pages)"
PAGE_TOK = f"(SELECT *, CAST(len({TOK}) AS BIGINT) AS n_tokens, lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]+)', 1)) AS host, lower(regexp_extract(url, '^([A-Za-z][A-Za-z0-9+.-]*)://', 1)) AS scheme FROM {PAGES})"
CELL = f"CAST(('0x' || substr(md5(gram), 1, 8)) AS BIGINT) % {SPEC.m}"


def _shares_sql(source: str, key: str, n: str, k: int | None = None) -> str:
    limit = f" QUALIFY row_number() OVER (PARTITION BY corpus ORDER BY n DESC, {key}) <= {k}" if k else ""
    return f"SELECT corpus, {key}, n, round(n / sum(n) OVER (PARTITION BY corpus), 6) AS share FROM (SELECT corpus, {key}, CAST({n} AS BIGINT) AS n FROM {source} WHERE {key} IS NOT NULL AND {key} <> '' GROUP BY corpus, {key}){limit}"


# --- summary, tokens, n-grams ---------------------------------------------------------------
SUMMARY_SQL = f"""SELECT corpus, count(*) AS n_docs, CAST(sum(octet_length(encode(text))) AS BIGINT) AS n_bytes, CAST(sum(length(text)) AS BIGINT) AS n_chars,
CAST(sum(n_tokens) AS BIGINT) AS n_tokens, max(n_tokens) AS max_tokens, min(n_tokens) AS min_tokens, count(*) FILTER ({BLANK}) AS n_blank, round(avg(n_tokens), 6) AS mean_tokens
FROM {DOCS} GROUP BY corpus"""


@register("summary_stats", SUMMARY_SQL)
def summary_stats(spark, sf):
    return stats.summary(documents(spark, sf))


@register("summary_by_subset", f"SELECT corpus, lang AS subset, count(*) AS n_docs, CAST(sum(n_tokens) AS BIGINT) AS n_tokens FROM {DOCS} GROUP BY ROLLUP (corpus, lang)")
def summary_by_subset(spark, sf):
    return stats.subset_rollup(documents(spark, sf))


for _name, _long in (("longest_documents", True), ("shortest_documents", False)):
    @register(_name, f"SELECT corpus, doc_id, n_tokens FROM {DOCS} QUALIFY row_number() OVER (PARTITION BY corpus ORDER BY n_tokens {'DESC' if _long else 'ASC'}, doc_id) = 1")
    def _extreme(spark, sf, longest=_long):
        return stats.extremes(documents(spark, sf), longest)


@register("token_counts", f"SELECT doc_id, n_tokens FROM {DOCS}")
def token_counts(spark, sf):
    return documents(spark, sf).select("doc_id", n_tokens("text").alias("n_tokens"))


@register("token_counts_whitespace", r"SELECT doc_id, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\s\p{Z}\x0B]+')) AS BIGINT) AS n_tokens FROM documents")
def token_counts_whitespace(spark, sf):
    return documents(spark, sf).select("doc_id", n_tokens("text", "whitespace").alias("n_tokens"))


@register("ngrams_n", f"SELECT doc_id, greatest(0, n_tokens - 1) AS n_grams FROM {DOCS}")
def ngrams_n(spark, sf):
    docs = texts(spark, sf)
    counted = grams(docs, 2, keep=["doc_id"]).groupBy("doc_id").agg(F.count("*").alias("n"))
    return docs.select("doc_id").join(counted, "doc_id", "left").select("doc_id", F.coalesce("n", F.lit(0)).alias("n_grams"))


def _top_sql(n: int, order: str = "DESC", k: int = K) -> str:
    return f"SELECT gram, count(*) AS cnt FROM {grams_sql(n)} GROUP BY gram ORDER BY cnt {order}, gram LIMIT {k}"


for _name, _n in (("top_unigrams", 1), ("top_bigrams", 2), ("top_trigrams", 3), ("top_5grams", 5), ("top_10grams", 10), ("top_100grams", 100)):
    @register(_name, _top_sql(_n))
    def _top(spark, sf, n=_n):
        return ngrams.top_exact(texts(spark, sf), n, K)


@register("bottom_ngrams_exact", _top_sql(1, "ASC"))
def bottom_ngrams_exact(spark, sf):
    return ngrams.bottom_exact(texts(spark, sf), 1, K)


BY_CORPUS_SQL = f"SELECT corpus, gram, count(*) AS cnt FROM {grams_sql(1)} GROUP BY corpus, gram"


@register("top_ngrams_by_corpus", f"SELECT corpus, gram, cnt, CAST(row_number() OVER (PARTITION BY corpus ORDER BY cnt DESC, gram) AS INTEGER) AS rnk FROM ({BY_CORPUS_SQL}) QUALIFY rnk <= 5")
def top_ngrams_by_corpus(spark, sf):
    return ngrams.top_by_corpus(texts(spark, sf), 1, 5)


#: Length of the published lists of each corpus.
LIST = 10_000
for _n in (1, 2, 3, 10):
    @register(f"top_lists_{_n}grams", f"SELECT corpus, gram, cnt, CAST(row_number() OVER (PARTITION BY corpus ORDER BY cnt DESC, gram) AS INTEGER) AS rnk FROM (SELECT corpus, gram, count(*) AS cnt FROM {grams_sql(_n)} GROUP BY corpus, gram) QUALIFY rnk <= {LIST}")
    def _lists(spark, sf, n=_n):
        """The published list of each corpus: its 10,000 most frequent n-grams."""
        return ngrams.top_by_corpus(texts(spark, sf), n, LIST)


CELLS_SQL = f"SELECT {CELL} AS cell, count(*) AS cnt FROM {grams_sql(1)} GROUP BY ALL"


@register("hashed_cells", f"SELECT cell, cnt, false AS saturated FROM ({CELLS_SQL})")
def hashed_cells(spark, sf):
    return cell_counts(grams(texts(spark, sf), 1), "gram", SPEC)


@register("hashed_cells_u32", f"SELECT cell, least(cnt, 4294967295) AS cnt, cnt >= 4294967295 AS saturated FROM ({CELLS_SQL})")
def hashed_cells_u32(spark, sf):
    return cell_counts(grams(texts(spark, sf), 1), "gram", HashSpec(SPEC.m, fn=SPEC.fn, counter="u32"))


def _hashed_sql(order: str, n: int = 1, k: int = K) -> str:
    cells = CELLS_SQL.replace(grams_sql(1), grams_sql(n))
    return f"WITH c AS ({cells}), g AS (SELECT DISTINCT gram FROM {grams_sql(n)}) SELECT gram, cnt AS est_cnt FROM g JOIN c ON {CELL} = cell ORDER BY cnt {order}, gram LIMIT {k}"


@register("top_ngrams_hashed", _hashed_sql("DESC", 2))
def top_ngrams_hashed(spark, sf):
    return ngrams.top_hashed(texts(spark, sf), 2, K, SPEC)


for _n in (1, 2, 3, 10):
    @register(f"top_{_n}grams_hashed_list", _hashed_sql("DESC", _n, LIST))
    def _hashed_list(spark, sf, n=_n):
        """The published length of list by hashed cells, over all corpora."""
        return ngrams.top_hashed(texts(spark, sf), n, LIST, SPEC)


@register("top_ngrams_sweep", _hashed_sql("DESC"))
def top_ngrams_sweep(spark, sf):
    return ngrams.top_sweep(texts(spark, sf), 1, K, SPEC)


#: Production cells: the fast hash, and so many cells that these tables have no collision.
WIDE = HashSpec(2**48)
for _name, _n in (("top_100grams_wide", 100), ("top_10grams_wide", 10), ("top_5grams_wide", 5), ("top_bigrams_wide", 2), ("top_trigrams_wide", 3), ("top_unigrams_wide", 1)):
    @register(_name, f"SELECT gram, cnt AS est_cnt FROM ({_top_sql(_n)})")
    def _wide(spark, sf, n=_n):
        return ngrams.top_hashed(texts(spark, sf), n, K, WIDE)


@register("bottom_ngrams_hashed", _hashed_sql("ASC"))
def bottom_ngrams_hashed(spark, sf):
    return ngrams.bottom_hashed(texts(spark, sf), 1, K, SPEC)


@register("top_ngrams_certified", f"WITH c AS ({CELLS_SQL}) SELECT gram, t.cnt, c.cnt AS est_cnt FROM ({_top_sql(1)}) t JOIN c ON {CELL} = cell")
def top_ngrams_certified(spark, sf):
    return ngrams.top_certified(texts(spark, sf), 1, K, SPEC).filter("certified").select("gram", "cnt", "est_cnt")


SET_SQL = f"SELECT corpus, count(DISTINCT {CELL}) AS set_cells, CAST({SPEC.m} AS BIGINT) AS table_cells FROM {grams_sql(1)} GROUP BY corpus"


@register("distinct_ngrams_bitmap", f"SELECT *, round(set_cells / table_cells, 6) AS occupancy FROM ({SET_SQL})")
def distinct_ngrams_bitmap(spark, sf):
    return occupancy(grams(texts(spark, sf), 1, keep=["corpus"]), "gram", SPEC, ["corpus"]).drop("linear_est", "nearly_full")


@register("distinct_ngrams_linear", f"SELECT corpus, CAST(round(-{float(SPEC.m)} * ln(1 - set_cells / table_cells), 0) AS BIGINT) AS linear_est, set_cells / table_cells > 0.9 AS nearly_full FROM ({SET_SQL})")
def distinct_ngrams_linear(spark, sf):
    return occupancy(grams(texts(spark, sf), 1, keep=["corpus"]), "gram", SPEC, ["corpus"]).select("corpus", "linear_est", "nearly_full")


@register("distinct_ngrams_exact", f"SELECT corpus, count(DISTINCT gram) AS n_distinct, round(count(DISTINCT gram) / count(*), 6) AS share_of_tokens FROM {grams_sql(1)} GROUP BY corpus")
def distinct_ngrams_exact(spark, sf):
    return ngrams.distinct_exact(texts(spark, sf), 1)


@register("singleton_ngrams", f"SELECT gram FROM (SELECT gram FROM {grams_sql(1)} GROUP BY gram HAVING count(*) = 1) ORDER BY md5('s' || gram), gram LIMIT 25")
def singleton_ngrams(spark, sf):
    return ngrams.singletons(texts(spark, sf))


EST_SQL = f"SELECT gram, cnt, sum(cnt) OVER (PARTITION BY {CELL}) AS est FROM (SELECT gram, count(*) AS cnt FROM {grams_sql(1)} GROUP BY gram)"


@register("hash_error", f"SELECT count(*) AS n_grams, count(*) FILTER (est > cnt) AS n_inflated, CAST(max(est - cnt) AS BIGINT) AS max_inflation FROM ({EST_SQL})")
def hash_error(spark, sf):
    return accuracy.error_report(grams(texts(spark, sf), 1), "gram", SPEC)


@register("hash_bound_check", f"SELECT gram, cnt, CAST(est AS BIGINT) AS est FROM ({EST_SQL}) WHERE est < cnt")
def hash_bound_check(spark, sf):
    return accuracy.bound_check(grams(texts(spark, sf), 1), "gram", SPEC).select("gram", "cnt", "est")


@register("hash_collisions", f"SELECT CAST({SPEC.m} AS BIGINT) AS table_cells, count(*) AS set_cells, count(*) FILTER (n > 1) AS colliding_cells, CAST(sum(n) AS BIGINT) AS n_keys, round(sum(n) / {SPEC.m}, 6) AS load FROM (SELECT {CELL} AS cell, count(DISTINCT gram) AS n FROM {grams_sql(1)} GROUP BY ALL)")
def hash_collisions(spark, sf):
    return accuracy.collision_report(grams(texts(spark, sf), 1), "gram", SPEC)


def _quality_sql(order: str) -> str:
    return f"WITH f AS ({_hashed_sql(order)}), t AS ({_top_sql(1, order)}) SELECT count(f.gram) AS n_found, count(t.gram) AS n_truth, count(*) FILTER (f.gram IS NOT NULL AND t.gram IS NOT NULL) AS n_both, round(count(*) FILTER (f.gram IS NOT NULL AND t.gram IS NOT NULL) / count(f.gram), 6) AS precision, round(count(*) FILTER (f.gram IS NOT NULL AND t.gram IS NOT NULL) / count(t.gram), 6) AS recall FROM f FULL JOIN t ON f.gram = t.gram"


@register("topk_quality", _quality_sql("DESC"))
def topk_quality(spark, sf):
    docs = texts(spark, sf)
    return accuracy.answer_quality(ngrams.top_hashed(docs, 1, K, SPEC), ngrams.top_exact(docs, 1, K))


@register("bottomk_quality", _quality_sql("ASC"))
def bottomk_quality(spark, sf):
    docs = texts(spark, sf)
    return accuracy.answer_quality(ngrams.bottom_hashed(docs, 1, K, SPEC), ngrams.bottom_exact(docs, 1, K))


@register("context_sample", f"""WITH h AS (SELECT DISTINCT doc_id FROM {grams_sql(2)} WHERE gram = 'of the'), c AS (SELECT doc_id FROM h ORDER BY md5('c' || CAST(doc_id AS VARCHAR)), doc_id LIMIT 100)
SELECT doc_id, substr(text, greatest(1, instr(text, 'of') - 40), 80) AS excerpt FROM documents JOIN c USING (doc_id)""")
def context_sample(spark, sf):
    return ngrams.context_sample(texts(spark, sf), "of the", 2)


@register("sketch_distinct")
def sketch_distinct(spark, sf):
    return sketches.distinct(grams(texts(spark, sf), 1), "gram")


@register("sketch_top")
def sketch_top(spark, sf):
    return sketches.top(grams(texts(spark, sf), 1), "gram", K)


_WITHIN = "SELECT * FROM (VALUES ('approx', true), ('hll', true), ('theta', true)) AS v(sketch, within)"


@register("sketch_distinct_error", _WITHIN)
def sketch_distinct_error(spark, sf):
    """Whether each sketch of the distinct tokens lies within a tenth of the exact number."""
    words = grams(texts(spark, sf), 1)
    exact = words.agg(F.countDistinct("gram").alias("exact"))
    found = sketches.distinct(words, "gram").join(F.broadcast(exact))
    near = lambda c: F.abs(F.col(c) / F.col("exact") - 1) <= 0.1
    return found.select(F.explode(F.array(*(F.struct(F.lit(c).alias("sketch"), near(c).alias("within")) for c in ("approx", "hll", "theta")))).alias("x")).select("x.sketch", "x.within")


@register("sketch_frequency_error", f"SELECT gram, true AS within FROM ({_top_sql(1)})")
def sketch_frequency_error(spark, sf):
    """Whether the count-min estimate of each frequent token is no less than its count and at most a thousandth of all tokens above it."""
    words = grams(texts(spark, sf), 1)
    truth = ngrams.top_exact(texts(spark, sf), 1, K)
    return sketches.held(sketches.frequencies(words, "gram"), truth, "gram", words.count(), 0.001)


# --- domains, dates, places, languages --------------------------------------------------------
@register("domains_by_doc", _shares_sql(PAGE_TOK, "host", "count(*)", 10))
def domains_by_doc(spark, sf):
    return domains.hosts(pages(spark, sf), "docs")


@register("domains_by_token", _shares_sql(PAGE_TOK, "host", "sum(n_tokens)", 10))
def domains_by_token(spark, sf):
    return domains.hosts(pages(spark, sf), "tokens")


_Q = {"q01": 0.01, "q25": 0.25, "q50": 0.5, "q75": 0.75, "q99": 0.99}


@register("domain_quantiles", f"SELECT corpus, {', '.join(f'round(quantile_cont(t, {q}), 6) AS {n}' for n, q in _Q.items())}, count(*) AS n_hosts FROM (SELECT corpus, host, sum(n_tokens) AS t FROM {PAGE_TOK} WHERE host <> '' GROUP BY corpus, host) GROUP BY corpus")
def domain_quantiles(spark, sf):
    return domains.quantiles(pages(spark, sf))


@register("url_schemes", _shares_sql(PAGE_TOK, "scheme", "count(*)"))
def url_schemes(spark, sf):
    return domains.schemes(pages(spark, sf))


@register("url_schemes_reference", f"SELECT corpus, scheme, share, CAST({domains.HTTPS_REFERENCE} AS DOUBLE) AS reference, round(share - {domains.HTTPS_REFERENCE}, 6) AS gap FROM ({_shares_sql(PAGE_TOK, 'scheme', 'count(*)')}) WHERE scheme = 'https'")
def url_schemes_reference(spark, sf):
    ref = F.lit(domains.HTTPS_REFERENCE)
    return domains.schemes(pages(spark, sf)).filter("scheme = 'https'").select("corpus", "scheme", "share", ref.alias("reference"), F.round(F.col("share") - ref, 6).alias("gap"))


_SUFFIX_SQL = "CASE " + " ".join(f"WHEN host = '{s}' OR ends_with(host, '.{s}') THEN '{s}'" for s in sorted(lexicons.PUBLIC_SUFFIXES, key=lambda s: (-s.count("."), s))) + " ELSE split_part(host, '.', -1) END"


@register("url_suffixes", _shares_sql(f"(SELECT corpus, {_SUFFIX_SQL} AS suffix FROM {PAGE_TOK} WHERE host <> '')", "suffix", "count(*)", 10))
def url_suffixes(spark, sf):
    return domains.suffixes(pages(spark, sf), lexicons.PUBLIC_SUFFIXES)


@register("url_suffixes_by_table", ORACLES["url_suffixes"])
def url_suffixes_by_table(spark, sf):
    known = _local(spark, [(s,) for s in lexicons.PUBLIC_SUFFIXES], "suffix string")
    return domains.suffixes_by_table(pages(spark, sf), known)


def _year_sql(source: str) -> str:
    return f"SELECT corpus, yr, n, round(n / sum(n) OVER (PARTITION BY corpus), 6) AS frac FROM (SELECT corpus, CAST(year(dt) AS INTEGER) AS yr, count(*) AS n FROM {source} WHERE dt IS NOT NULL GROUP BY ALL)"


@register("docs_per_year", _year_sql("(SELECT o_orderpriority AS corpus, o_orderdate AS dt FROM orders)"))
def docs_per_year(spark, sf):
    return dates.by_year(table(spark, sf, "orders").select(F.col("o_orderpriority").alias("corpus"), F.col("o_orderdate").alias("created")))


@register("docs_per_year_estimated", _year_sql("(SELECT corpus, CASE WHEN first_seen IS NULL THEN o_orderdate ELSE least(o_orderdate, first_seen) END AS dt FROM (SELECT o_orderkey, o_orderpriority AS corpus, o_orderdate FROM orders ORDER BY md5('y' || CAST(o_orderkey AS VARCHAR)), o_orderkey LIMIT 10000) o LEFT JOIN (SELECT l_orderkey, min(l_shipdate) AS first_seen FROM lineitem GROUP BY l_orderkey) l ON o_orderkey = l_orderkey)"))
def docs_per_year_estimated(spark, sf):
    orders = table(spark, sf, "orders").select(F.col("o_orderkey").alias("key"), F.col("o_orderpriority").alias("corpus"), F.col("o_orderdate").alias("created"))
    seen = table(spark, sf, "lineitem").select(F.col("l_orderkey").alias("key"), F.col("l_shipdate").alias("first_seen"))
    return dates.by_year_estimated(orders, seen, "key")


IP_SQL = rf"""(SELECT doc_id, corpus, 'ip' AS kind, unnest(list_filter(regexp_extract_all(text, '{pii.IP}'), lambda v:
NOT regexp_matches(substr(text, greatest(1, instr(text, v) - 50), length(v) + 50 + least(50, instr(text, v) - 1)), '(?i)isbn|doi')
AND NOT contains(substr(text, greatest(1, instr(text, v) - 50), length(v) + 50 + least(50, instr(text, v) - 1)), '#'))) AS value FROM {DOCS})"""
_GEO_ROWS = "(SELECT b * 16777216 AS lo, b * 16777216 + 16777215 AS hi, n_name AS country FROM range(256) r(b) JOIN nation ON b % 25 = n_nationkey WHERE b % 10 <> 3)"
_IPN = " + ".join(f"CAST(split_part(value, '.', {k + 1}) AS BIGINT) * {1 << 8 * (3 - k)}" for k in range(4))


def _ip_ranges(spark: SparkSession, sf: str) -> DataFrame:
    """Blocks of 2^24 addresses dealt to the nations; some belong to none."""
    nation = F.broadcast(table(spark, sf, "nation").select("n_nationkey", F.col("n_name").alias("country")))
    block = spark.range(256).filter("id % 10 <> 3")
    return block.join(nation, F.col("id") % 25 == F.col("n_nationkey")).select((F.col("id") * 16777216).alias("lo"), (F.col("id") * 16777216 + 16777215).alias("hi"), "country")


def _geo_sql(where: str = "") -> str:
    return f"""WITH l AS (SELECT coalesce(country, 'UN') AS country FROM (SELECT value, {_IPN} AS num FROM {IP_SQL}) i LEFT JOIN {_GEO_ROWS} g ON num BETWEEN lo AND hi),
c AS (SELECT country, count(*) AS n FROM l {where} GROUP BY country), f AS (SELECT country FROM c ORDER BY n DESC, country LIMIT 9),
o AS (SELECT CASE WHEN country IN (SELECT country FROM f) THEN country ELSE 'other' END AS country, CAST(sum(n) AS BIGINT) AS n FROM c GROUP BY ALL)
SELECT country, n, round(n / sum(n) OVER (), 6) AS share FROM o"""


@register("geo_by_country", _geo_sql())
def geo_by_country(spark, sf):
    found = pii.find(documents(spark, sf), "ip").select(F.col("value").alias("ip"))
    return geo.countries(found, _ip_ranges(spark, sf))


@register("geo_by_country_known", _geo_sql("WHERE country <> 'UN'"))
def geo_by_country_known(spark, sf):
    found = pii.find(documents(spark, sf), "ip").select(F.col("value").alias("ip"))
    return geo.countries(found, _ip_ranges(spark, sf), drop_unknown=True)


@register("language_share", "SELECT corpus, lang, n, round(n / sum(n) OVER (PARTITION BY corpus), 6) AS share FROM (SELECT source AS corpus, coalesce(lang, 'UN') AS lang, count(*) AS n FROM documents GROUP BY ALL)")
def language_share(spark, sf):
    return language.share(documents(spark, sf))


_PROFILE_SQL = f"""c AS (SELECT doc_id, source, lang, regexp_replace(lower(coalesce(text, '')), '[^\\p{{L}}]+', ' ', 'g') AS c FROM documents),
g AS (SELECT doc_id, source, lang, substr(c, i, 3) AS gram FROM (SELECT *, unnest(range(1, length(c) - 1)) AS i FROM c WHERE length(c) >= 3)),
n AS (SELECT lang, gram, count(*) AS c FROM g WHERE lang IS NOT NULL AND doc_id % {language.FOLDS} <> {language.HELD} GROUP BY lang, gram QUALIFY row_number() OVER (PARTITION BY lang ORDER BY c DESC, gram) <= {language.SIZE}),
p AS (SELECT lang AS l, gram, ln(c / sum(c) OVER (PARTITION BY lang)) AS weight FROM n)"""
_DETECT_SQL = f"""{_PROFILE_SQL},
s AS (SELECT doc_id, l, round(sum(weight + {-language.UNSEEN}), 6) AS score FROM g JOIN p USING (gram) GROUP BY doc_id, l),
b AS (SELECT doc_id, l FROM s QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY score DESC, l) = 1),
d AS (SELECT t.doc_id, t.source, t.lang AS given, coalesce(l, 'UN') AS lang FROM documents t LEFT JOIN b ON t.doc_id = b.doc_id)"""


@register("language_profiles", f"WITH {_PROFILE_SQL} SELECT l AS lang, gram, round(weight, 6) AS weight FROM p")
def language_profiles(spark, sf):
    return language.profiles(texts(spark, sf)).select("lang", "gram", F.round("weight", 6).alias("weight"))


@register("language_detected", f"WITH {_DETECT_SQL} SELECT doc_id, lang FROM d")
def language_detected(spark, sf):
    docs = texts(spark, sf)
    return language.detect(docs, language.profiles(docs)).select("doc_id", "lang")


@register("language_accuracy", f"WITH {_DETECT_SQL} SELECT given AS lang, count(*) AS n, count(*) FILTER (lang = given) AS n_right, round(count(*) FILTER (lang = given) / count(*), 6) AS accuracy FROM d WHERE doc_id % {language.FOLDS} = {language.HELD} AND given IS NOT NULL GROUP BY given")
def language_accuracy(spark, sf):
    """The detector on documents that it never learned from."""
    return language.accuracy(language_detected(spark, sf), documents(spark, sf))


@register("language_detected_share", f"WITH {_DETECT_SQL} SELECT corpus, lang, n, round(n / sum(n) OVER (PARTITION BY corpus), 6) AS share FROM (SELECT source AS corpus, lang, count(*) AS n FROM d GROUP BY ALL)")
def language_detected_share(spark, sf):
    """Languages of each corpus by detection."""
    found = language_detected(spark, sf).withColumnRenamed("lang", "found")
    return language.share(documents(spark, sf).select("doc_id", "corpus").join(found, "doc_id"), "found")


# --- duplicates and lengths -------------------------------------------------------------------
def _dup_sql(source: str, column: str) -> str:
    return f"""SELECT corpus, CAST(sum(size) AS BIGINT) AS n_docs, CAST(sum(CASE WHEN size > 1 THEN size ELSE 0 END) AS BIGINT) AS dup_docs, round(sum(CASE WHEN size > 1 THEN size ELSE 0 END) / sum(size), 6) AS doc_ratio,
count(*) FILTER (size > 1) AS dup_clusters, round(count(*) FILTER (size > 1) / count(*), 6) AS cluster_ratio, CAST(sum(CASE WHEN size > 1 THEN size - 1 ELSE 0 END) AS BIGINT) AS surplus
FROM (SELECT corpus, count(*) AS size FROM {source} WHERE {column} IS NOT NULL GROUP BY corpus, {column}) GROUP BY corpus"""


DUP_SQL = _dup_sql("(SELECT source AS corpus, text FROM documents)", "text")


@register("text_duplicates", DUP_SQL)
def text_duplicates(spark, sf):
    return duplicates.stats(documents(spark, sf))


@register("url_duplicates", _dup_sql(PAGES, "url"))
def url_duplicates(spark, sf):
    return duplicates.stats(pages(spark, sf), "url")


@register("text_duplicates_all", _dup_sql("(SELECT 'all' AS corpus, text FROM documents)", "text"))
def text_duplicates_all(spark, sf):
    return duplicates.stats(documents(spark, sf).withColumn("corpus", F.lit("all")))


@register("duplicate_keys_bytes", "SELECT corpus, CAST(sum(b) AS BIGINT) AS string_bytes, 16 * count(*) AS digest_bytes, round(sum(b) / (16 * count(*)), 6) AS ratio FROM (SELECT DISTINCT source AS corpus, text, octet_length(encode(text)) AS b FROM documents WHERE text IS NOT NULL) GROUP BY corpus")
def duplicate_keys_bytes(spark, sf):
    """What the keys of a duplicate search weigh as texts and as digests."""
    return duplicates.key_bytes(documents(spark, sf))


@register("text_duplicates_by_string", ORACLES["text_duplicates_all"])
def text_duplicates_by_string(spark, sf):
    """The baseline that keeps every string: the texts themselves are shuffled."""
    size = F.col("size")
    dup, many = F.sum(F.when(size > 1, size).otherwise(0)), F.count_if(size > 1)
    counted = documents(spark, sf).filter(F.col("text").isNotNull()).groupBy("text").agg(F.count("*").alias("size"))
    return counted.agg(F.sum("size").alias("n_docs"), dup.alias("dup_docs"), F.round(dup / F.sum("size"), 6).alias("doc_ratio"), many.alias("dup_clusters"), F.round(many / F.count("*"), 6).alias("cluster_ratio"), (dup - many).alias("surplus")).withColumn("corpus", F.lit("all"))


_CLUSTERS = "(SELECT text, count(*) AS size FROM documents WHERE text IS NOT NULL GROUP BY text HAVING count(*) > 1)"


@register("top_duplicate_texts", f"SELECT CAST(row_number() OVER (ORDER BY size DESC, upper(md5(text))) AS INTEGER) AS rnk, size AS cnt, substr(text, 1, 100) AS excerpt FROM {_CLUSTERS} QUALIFY rnk <= 5")
def top_duplicate_texts(spark, sf):
    return duplicates.top(documents(spark, sf))


@register("duplicate_size_histogram", f"SELECT size, clusters, docs, round(sum(docs) OVER (ORDER BY size DESC ROWS UNBOUNDED PRECEDING) / sum(docs) OVER (), 6) AS cum_share FROM (SELECT size, count(*) AS clusters, CAST(sum(size) AS BIGINT) AS docs FROM {_CLUSTERS} GROUP BY size)")
def duplicate_size_histogram(spark, sf):
    return duplicates.sizes(documents(spark, sf))


@register("duplicate_cross_key", f"SELECT key, n, count(DISTINCT source) AS n_other FROM documents JOIN (SELECT text AS key, size AS n FROM {_CLUSTERS} ORDER BY size DESC, text LIMIT 25) ON text = key GROUP BY key, n")
def duplicate_cross_key(spark, sf):
    return duplicates.cross_key(table(spark, sf, "documents"), "text", "source")


def _seed_sizes(s: int) -> str:
    return f"(SELECT size, count(*) AS n FROM (SELECT count(*) AS size FROM documents GROUP BY md5('{s}' || text)) GROUP BY size)"


@register("duplicate_seed_check", f"SELECT size, diff FROM (SELECT coalesce(a.size, b.size) AS size, coalesce(a.n, 0) - coalesce(b.n, 0) AS diff FROM {_seed_sizes(1)} a FULL JOIN {_seed_sizes(2)} b ON a.size = b.size) WHERE diff <> 0")
def duplicate_seed_check(spark, sf):
    return accuracy.seed_agreement(documents(spark, sf), "text")


def _hist_sql(value: str) -> str:
    return f"SELECT length, n, round(n / sum(n) OVER (), 6) AS share FROM (SELECT {value} AS length, count(*) AS n FROM {DOCS} GROUP BY ALL)"


_CHARS = "CAST(length(text) AS BIGINT)"


@register("length_histogram_chars", _hist_sql(_CHARS))
def length_histogram_chars(spark, sf):
    return lengths.histogram(documents(spark, sf))


@register("length_histogram_tokens", _hist_sql("n_tokens"))
def length_histogram_tokens(spark, sf):
    return lengths.histogram(documents(spark, sf), "tokens")


@register("length_histogram_log", f"SELECT corpus, CASE WHEN length(text) > 0 THEN CAST(floor(round(log10(length(text)) * 10, 6)) AS BIGINT) ELSE -1 END AS bin, count(*) AS n FROM {DOCS} GROUP BY ALL")
def length_histogram_log(spark, sf):
    return lengths.log_histogram(documents(spark, sf))


OUTLIER_SQL = f"SELECT length, n, round(m, 6) AS neighbour_mean FROM (SELECT length, n, (sum(n) OVER (ORDER BY length RANGE BETWEEN 10 PRECEDING AND 10 FOLLOWING) - n) / 20.0 AS m FROM ({_hist_sql(_CHARS)})) WHERE n >= 3 AND n >= 5 * m"


@register("length_outliers", OUTLIER_SQL)
def length_outliers(spark, sf):
    return lengths.outliers(lengths.histogram(documents(spark, sf)))


@register("length_medians", f"SELECT corpus, CAST(median(n_tokens) AS DOUBLE) AS median_tokens, CAST(median(length(text)) AS DOUBLE) AS median_chars FROM {DOCS} GROUP BY corpus")
def length_medians(spark, sf):
    return lengths.medians(documents(spark, sf))


@register("template_clusters", f"SELECT substr(regexp_replace(text, '[0-9]+', '0', 'g'), 1, 60) AS template, count(*) AS n FROM {DOCS} WHERE {_CHARS} IN (SELECT length FROM ({OUTLIER_SQL})) GROUP BY ALL HAVING count(*) > 1")
def template_clusters(spark, sf):
    docs = documents(spark, sf)
    return lengths.templates(docs, lengths.outliers(lengths.histogram(docs)))


# --- search -----------------------------------------------------------------------------------
TERMS = ["the", "de", "and", "worthless", "best"]


@register("term_doc_frequency", f"SELECT t.term, coalesce(df, 0) AS df, coalesce(tf, 0) AS tf FROM {_values([(t,) for t in TERMS], 'term')} t LEFT JOIN (SELECT gram, count(DISTINCT doc_id) AS df, count(*) AS tf FROM {grams_sql(1)} GROUP BY gram) g ON g.gram = t.term")
def term_doc_frequency(spark, sf):
    return query.frequency(index.build(texts(spark, sf)), [[t] for t in TERMS]).withColumnRenamed("phrase", "term")


@register("term_frequency", "SELECT term, df, tf FROM (" + ORACLES["term_doc_frequency"] + ") WHERE tf > 0")
def term_frequency(spark, sf):
    """Corpus frequencies of the terms that a model is asked about: one pass for a list of terms, no index needed."""
    asked = _local(spark, [(t,) for t in TERMS], "term string")
    return grams(texts(spark, sf), 1, keep=["doc_id"]).withColumnRenamed("gram", "term").join(asked, "term").groupBy("term", "doc_id").agg(F.count("*").alias("n")).groupBy("term").agg(F.count("*").alias("df"), F.sum("n").alias("tf"))


@register("ngram_count_by_search", f"SELECT 'of the' AS gram, count(DISTINCT doc_id) AS df, count(*) AS tf FROM {grams_sql(2)} WHERE gram = 'of the'")
def ngram_count_by_search(spark, sf):
    return query.ngram_counts(index.build(texts(spark, sf)), "of the")


_HAS = "SELECT doc_id FROM {0} WHERE gram = '{1}'"
_BOOLEAN = f"SELECT DISTINCT doc_id FROM documents WHERE (doc_id IN ({_HAS.format(grams_sql(1), 'the')}) AND doc_id IN ({_HAS.format(grams_sql(2), 'of the')}) OR doc_id IN ({_HAS.format(grams_sql(1), 'best')})) AND doc_id NOT IN ({_HAS.format(grams_sql(1), 'with')})"
EXPRESSION = query.And((query.Or((query.And((query.Term("the"), query.Phrase(("of", "the")))), query.Term("best"))), query.Not(query.Term("with"))))


@register("boolean_search", _BOOLEAN)
def boolean_search(spark, sf):
    return query.run(index.build(texts(spark, sf)), EXPRESSION)


@register("retrieve_documents", f"SELECT doc_id, text FROM documents WHERE doc_id IN ({_BOOLEAN} ORDER BY doc_id LIMIT {K})")
def retrieve_texts(spark, sf):
    docs = texts(spark, sf)
    return query.fetch(query.run(index.build(docs), EXPRESSION), docs, K).select("doc_id", "text")


# --- contamination ------------------------------------------------------------------------------
ITEMS = f"(SELECT item_id, list_filter(list_transform(regexp_extract_all(text, '{contamination.SENTENCE}'), lambda s: trim(s)), lambda s: s <> '') AS fields FROM benchmark)"
HITS = f"(SELECT doc_id, item_id, n_fields, n FROM (SELECT doc_id, item_id, len(fields) AS n_fields, len(list_filter(fields, lambda f: contains(text, f))) AS n FROM documents, {ITEMS}) WHERE n > 0)"
ALL_HITS = f"(SELECT doc_id, item_id FROM {HITS} WHERE n = n_fields)"


def _items(spark: SparkSession, sf: str) -> DataFrame:
    return contamination.items_from_text(table(spark, sf, "benchmark"))


for _name, _method in (("contamination_items", "scan"), ("contamination_items_index", "index")):
    @register(_name, f"SELECT i.item_id, CAST(len(fields) AS BIGINT) AS n_fields, count(DISTINCT doc_id) AS n_docs FROM {ITEMS} i LEFT JOIN {ALL_HITS} h ON i.item_id = h.item_id GROUP BY ALL")
    def _contaminated(spark, sf, method=_method):
        items = _items(spark, sf)
        return contamination.per_item(contamination.evaluate(texts(spark, sf), items, method), items)


def _rate_sql(hits: str, items: str = ITEMS) -> str:
    return f"SELECT c.corpus, n_items, coalesce(n_hit, 0) AS n_hit, round(coalesce(n_hit, 0) / n_items, 6) AS rate FROM (SELECT DISTINCT source AS corpus FROM documents) c LEFT JOIN (SELECT source AS corpus, count(DISTINCT item_id) AS n_hit FROM {hits} h JOIN documents USING (doc_id) GROUP BY ALL) h ON c.corpus = h.corpus, (SELECT count(*) AS n_items FROM {items})"


@register("contamination_rate", _rate_sql(ALL_HITS))
def contamination_rate(spark, sf):
    docs, items = texts(spark, sf), _items(spark, sf)
    return contamination.rate(contamination.evaluate(docs, items), docs, items)


@register("contamination_rate_eligible", _rate_sql(f"(SELECT doc_id, item_id FROM {HITS} WHERE n = n_fields AND n_fields >= 2)", f"(SELECT * FROM {ITEMS} WHERE len(fields) >= 2)"))
def contamination_rate_eligible(spark, sf):
    docs, items = texts(spark, sf), contamination.eligible(_items(spark, sf))
    return contamination.rate(contamination.evaluate(docs, items), docs, items)


@register("contamination_any_field", f"SELECT corpus, rate FROM ({_rate_sql(HITS)})")
def contamination_any_field(spark, sf):
    docs, items = texts(spark, sf), _items(spark, sf)
    return contamination.rate(contamination.evaluate(docs, items, require="any"), docs, items).select("corpus", "rate")


_TURNS = "(SELECT conv_id AS item_id, list(text ORDER BY turn) AS fields FROM conversations GROUP BY conv_id)"


def _set_sql(name: str, items: str) -> str:
    hits = ALL_HITS.replace(ITEMS, items)
    return f"SELECT '{name}' AS set, corpus, rate FROM ({_rate_sql(hits, items)})"


@register("contamination_report", f"SELECT set, max(rate) AS max_rate, max(rate) >= 0.05 AS above_threshold, max(rate) = 0 AS is_zero FROM ({_set_sql('benchmark', ITEMS)} UNION ALL {_set_sql('conversations', _TURNS)}) GROUP BY set")
def contamination_report(spark, sf):
    docs = texts(spark, sf)
    turns = table(spark, sf, "conversations").groupBy(F.col("conv_id").alias("item_id")).agg(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda t: t["text"]).alias("fields"))
    rates = [contamination.rate(contamination.evaluate(docs, items, "index"), docs, items).select(F.lit(name).alias("set"), "corpus", "rate") for name, items in (("benchmark", _items(spark, sf)), ("conversations", turns))]
    return contamination.report(rates[0].union(rates[1]))


@register("contamination_bound", f"SELECT item_id, count(DISTINCT CASE WHEN n = n_fields THEN doc_id END) AS n_all, count(DISTINCT doc_id) AS n_any, bool_and(n = n_fields OR n < n_fields) AS bounded FROM {HITS} GROUP BY item_id")
def contamination_bound(spark, sf):
    """Documents with all fields of an item against those with any: the former are never more."""
    docs, items = texts(spark, sf), _items(spark, sf)
    counted = [contamination.per_item(contamination.evaluate(docs, items, "index", r), items).select("item_id", F.col("n_docs").alias(f"n_{r}")) for r in ("all", "any")]
    met = counted[0].join(counted[1], "item_id").filter("n_any > 0")
    return met.select("item_id", "n_all", "n_any", (F.col("n_all") <= F.col("n_any")).alias("bounded"))


@register("decontaminate", f"SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM {ALL_HITS})")
def decontaminate(spark, sf):
    docs = texts(spark, sf)
    return contamination.remove(docs, contamination.evaluate(docs, _items(spark, sf))).select("doc_id")


def _shingles_sql(source: str, key: str) -> str:
    return f"SELECT DISTINCT {key}, gram FROM {grams_sql(8, source, key)}"


@register("contamination_overlap", f"WITH i AS ({_shingles_sql('(SELECT item_id, array_to_string(fields, chr(32)) AS text FROM ' + ITEMS + ')', 'item_id')}), d AS ({_shingles_sql('documents', 'doc_id')}), n AS (SELECT item_id, count(*) AS n FROM i GROUP BY item_id) SELECT doc_id, item_id, round(count(*) / any_value(n), 6) AS overlap FROM i JOIN d USING (gram) JOIN n USING (item_id) GROUP BY doc_id, item_id HAVING overlap >= 0.5")
def contamination_overlap(spark, sf):
    return contamination.overlap(texts(spark, sf), _items(spark, sf))


# --- personal data ------------------------------------------------------------------------------
EMAIL_SQL = f"(SELECT doc_id, corpus, 'email' AS kind, unnest(list_filter(regexp_extract_all(text, '{pii.EMAIL}', 1), lambda v: split_part(v, '@', 1) <> '(' AND contains(split_part(v, '@', -1), '.'))) AS value FROM {DOCS})"
_NEAR = "substr(text, greatest(1, instr(text, v) - 50), length(v) + 50 + least(50, instr(text, v) - 1))"
PHONE_SQL = rf"(SELECT doc_id, corpus, 'phone' AS kind, unnest(list_filter(list_transform(regexp_extract_all(text, '{pii.PHONE}'), lambda x: regexp_replace(x, '^\s+', '')), lambda v: NOT regexp_matches({_NEAR}, '(?i)isbn|doi') AND NOT contains({_NEAR}, '#') AND NOT contains(array_to_string(regexp_extract_all(text, '{pii.URL}'), ' '), v))) AS value FROM {DOCS})"
ALL_PII = f"(SELECT * FROM {EMAIL_SQL} UNION ALL SELECT * FROM {PHONE_SQL} UNION ALL SELECT * FROM {IP_SQL})"
for _kind, _sql in (("email", EMAIL_SQL), ("phone", PHONE_SQL), ("ip", IP_SQL)):
    @register(f"pii_{_kind}", f"SELECT doc_id, value FROM {_sql}")
    def _pii(spark, sf, kind=_kind):
        return pii.find(documents(spark, sf), kind).select("doc_id", "value")


@register("pii_email_at_end", "SELECT doc_id, value FROM " + EMAIL_SQL.replace(pii.EMAIL, pii.EMAIL_AT_END))
def pii_email_at_end(spark, sf):
    return pii.find(documents(spark, sf), "email", at_end=True).select("doc_id", "value")


@register("pii_phone_closed", "SELECT doc_id, value FROM " + PHONE_SQL.replace(pii.PHONE, pii.PHONE_CLOSED))
def pii_phone_closed(spark, sf):
    return pii.find(documents(spark, sf), "phone", boundary="closed").select("doc_id", "value")


COUNTS_SQL = f"SELECT corpus, kind, count(*) AS n FROM {ALL_PII} GROUP BY ALL"


@register("pii_counts", COUNTS_SQL)
def pii_counts(spark, sf):
    return pii.counts(documents(spark, sf))


_STRICT_SQL = "CASE kind " + " ".join(f"WHEN '{k}' THEN regexp_matches(value, '{p}')" for k, p in pii.STRICT.items()) + " END"
PRECISION_SQL = f"SELECT corpus, kind, count(*) AS n, round(avg(CAST({_STRICT_SQL} AS DOUBLE)), 6) AS precision FROM (SELECT * FROM {ALL_PII} QUALIFY row_number() OVER (PARTITION BY corpus, kind ORDER BY md5('p' || CAST(doc_id AS VARCHAR) || ':' || value), doc_id, value) <= 100) GROUP BY ALL"


@register("pii_precision", PRECISION_SQL)
def pii_precision(spark, sf):
    return pii.precision(pii.judge(pii.sample_for_review(pii.find_all(documents(spark, sf)))))


EST_PII_SQL = f"SELECT corpus, kind, round(c.n * precision, 6) AS est FROM ({COUNTS_SQL}) c JOIN ({PRECISION_SQL}) p USING (corpus, kind)"


@register("pii_extrapolated", EST_PII_SQL)
def pii_extrapolated(spark, sf):
    return pii.extrapolate(pii_counts(spark, sf), pii_precision(spark, sf))


@register("pii_per_token", f"SELECT corpus, kind, round(est / t, 9) AS rate FROM ({EST_PII_SQL}) JOIN (SELECT corpus, sum(n_tokens) AS t FROM {DOCS} GROUP BY corpus) USING (corpus)")
def pii_per_token(spark, sf):
    docs = documents(spark, sf)
    return pii.rate(pii_extrapolated(spark, sf), docs.groupBy("corpus").agg(F.sum(n_tokens("text")).alias("n_tokens")))


_PLANTED = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}"


@register("pii_recall", f"SELECT corpus, count(*) AS n_planted, count(*) FILTER (found) AS n_found, round(count(*) FILTER (found) / count(*), 6) AS recall FROM (SELECT corpus, list_contains(coalesce(f, []), v) AS found FROM (SELECT doc_id, corpus, unnest(list_distinct(regexp_extract_all(text, '{_PLANTED}'))) AS v FROM {DOCS}) LEFT JOIN (SELECT doc_id, list(DISTINCT value) AS f FROM {EMAIL_SQL} GROUP BY doc_id) USING (doc_id)) GROUP BY corpus")
def pii_recall(spark, sf):
    """Share of the strictly formed addresses of each document that the rule finds, by corpus."""
    docs = documents(spark, sf)
    planted = docs.select("doc_id", "corpus", F.explode(F.array_distinct(F.regexp_extract_all("text", F.lit(_PLANTED), F.lit(0)))).alias("value"))
    return pii.recall(planted, pii.find(docs, "email"))


_MARKS = "(?:" + "|".join(rf"\{c}{{51,}}" for c in "!#$%&*+-./:;<=>?@^_~()") + ")"


@register("pii_prefilter", f"SELECT doc_id FROM documents WHERE NOT coalesce(regexp_matches(text, '{_MARKS}'), false)")
def pii_prefilter(spark, sf):
    return pii.prefilter(documents(spark, sf)).select("doc_id")


# --- toxicity and sentiment -----------------------------------------------------------------------
LEXICON_SQL = _values(list(lexicons.TOXIC_TERMS.items()), "term", "category")
WORDS_SQL = f"(SELECT doc_id, corpus, lower(gram) AS term FROM {grams_sql(1)} UNION ALL SELECT doc_id, corpus, lower(gram) AS term FROM {grams_sql(2)})"
MATCH_SQL = f"(SELECT doc_id, corpus, category, count(*) AS n FROM {WORDS_SQL} JOIN {LEXICON_SQL} USING (term) GROUP BY ALL)"
TOXIC_IDS_SQL = f"(SELECT DISTINCT doc_id FROM {MATCH_SQL} WHERE category IN {lexicons.OFFENSIVE})"


def _lexicon(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(lexicons.TOXIC_TERMS.items()), "term string, category string")


@register("toxic_taxonomy", f"SELECT corpus, category, CAST(sum(n) AS BIGINT) AS mentions, round(sum(n) / any_value(t), 9) AS per_token FROM {MATCH_SQL} JOIN (SELECT corpus, sum(n_tokens) AS t FROM {DOCS} GROUP BY corpus) USING (corpus) GROUP BY corpus, category")
def toxic_taxonomy(spark, sf):
    return toxicity.taxonomy(texts(spark, sf), _lexicon(spark))


@register("toxic_documents", f"SELECT source AS corpus, count(*) AS n_docs, count(h.doc_id) AS n_toxic, round(100 * count(h.doc_id) / count(*), 6) AS pct FROM documents d LEFT JOIN {TOXIC_IDS_SQL} h ON d.doc_id = h.doc_id GROUP BY source")
def toxic_texts(spark, sf):
    return toxicity.documents(texts(spark, sf), _lexicon(spark))


@register("toxic_lexicon_quality", f"SELECT count(*) FILTER (hit AND toxic = 1) AS tp, count(*) FILTER (hit AND toxic <> 1) AS fp, count(*) FILTER (NOT hit AND toxic = 1) AS fn, count(*) FILTER (NOT hit AND toxic <> 1) AS tn FROM (SELECT toxic, l.doc_id IN (SELECT doc_id FROM {TOXIC_IDS_SQL}) AS hit FROM labels l)")
def toxic_lexicon_quality(spark, sf):
    return toxicity.quality(toxicity.toxic_ids(texts(spark, sf), _lexicon(spark)), table(spark, sf, "labels"))


def _classified(spark: SparkSession, sf: str) -> DataFrame:
    """All documents by a classifier that left the held-out fold's labels alone."""
    docs = texts(spark, sf)
    return toxicity.classify(docs, toxicity.train(docs, table(spark, sf, "labels")))


@register("toxic_classifier")
def toxic_classifier(spark, sf):
    return _classified(spark, sf).select("doc_id", "toxic")


@register("toxic_classifier_documents")
def toxic_classifier_documents(spark, sf):
    """Documents of each corpus that hold a sentence which the classifier finds toxic, in percent."""
    return toxicity.share(_classified(spark, sf), documents(spark, sf))


@register("toxic_classifier_quality")
def toxic_classifier_quality(spark, sf):
    """Measures over the held-out fold."""
    return toxicity.scores(_classified(spark, sf).filter(toxicity.held_out()), table(spark, sf, "labels").filter(toxicity.held_out()))


@register("toxic_agreement")
def toxic_agreement(spark, sf):
    """Classifier against lexicon over all documents."""
    docs = texts(spark, sf)
    by_words = docs.select("doc_id").join(toxicity.toxic_ids(docs, _lexicon(spark)).withColumn("hit", F.lit(1)), "doc_id", "left").select("doc_id", F.coalesce("hit", F.lit(0)).alias("toxic"))
    return toxicity.agreement(toxic_classifier(spark, sf), by_words)


POLARITY_ROWS = [(t, float(s)) for t, s in lexicons.POLARITY.items()]
SENTENCES_SQL = f"(SELECT doc_id, s, list_transform({tokens_sql('sentence')}, lambda t: lower(t)) AS w FROM (SELECT doc_id, unnest(range(len(p))) AS s, unnest(p) AS sentence FROM (SELECT doc_id, list_filter(list_transform(regexp_extract_all(coalesce(text, ''), '{toxicity.SENTENCE}'), lambda x: trim(x)), lambda x: x <> '') AS p FROM documents)))"
SENT_TERMS_SQL = f"(SELECT DISTINCT doc_id, s, term FROM (SELECT doc_id, s, unnest(w) AS term FROM {SENTENCES_SQL} UNION ALL SELECT doc_id, s, w[i] || ' ' || w[i + 1] AS term FROM (SELECT doc_id, s, w, unnest(range(1, len(w))) AS i FROM {SENTENCES_SQL})))"
POLAR_SQL = f"(SELECT doc_id, s, coalesce(avg(score), 0.0) AS polarity FROM (SELECT doc_id, s, unnest(w) AS term FROM {SENTENCES_SQL}) LEFT JOIN {_values(POLARITY_ROWS, 'term', 'score')} USING (term) GROUP BY doc_id, s)"
GROUP_SQL = _values(lexicons.GROUP_TERMS, "grp", "term")


def _sentiment_args(spark: SparkSession, sf: str) -> tuple:
    return texts(spark, sf), spark.createDataFrame(lexicons.GROUP_TERMS, "grp string, term string"), spark.createDataFrame(POLARITY_ROWS, "term string, score double")


@register("demographic_sentiment", f"SELECT grp, term, count(*) AS n_sentences, round(avg(CAST(polarity AS DOUBLE)), 6) AS mean_polarity FROM {SENT_TERMS_SQL} JOIN {GROUP_SQL} USING (term) JOIN {POLAR_SQL} USING (doc_id, s) GROUP BY grp, term")
def demographic_sentiment(spark, sf):
    return sentiment.by_term(*_sentiment_args(spark, sf))


@register("demographic_sentiment_sample", "SELECT grp, term, n_sentences, mean_polarity FROM (" + ORACLES["demographic_sentiment"].replace("FROM documents", "FROM (SELECT * FROM documents WHERE CAST('0x' || substr(md5('t' || CAST(doc_id AS VARCHAR)), 1, 4) AS INTEGER) % 10 = 0)") + ")")
def demographic_sentiment_sample(spark, sf):
    """The published form: on a tenth of the documents, chosen by a hash of their ids."""
    docs, groups, scores = _sentiment_args(spark, sf)
    tenth = F.conv(F.substring(F.md5(F.concat(F.lit("t"), F.col("doc_id").cast("string")).cast("binary")), 1, 4), 16, 10).cast("long") % 10 == 0
    return sentiment.by_term(docs.filter(tenth), groups, scores)


@register("cooccurrence_sentiment", f"""WITH m AS (SELECT grp, t.term, x.term AS word, score, count(*) AS n FROM {SENT_TERMS_SQL} t JOIN {GROUP_SQL} USING (term) JOIN (SELECT DISTINCT doc_id, s, term FROM (SELECT doc_id, s, unnest(w) AS term FROM {SENTENCES_SQL})) x ON t.doc_id = x.doc_id AND t.s = x.s JOIN {_values(POLARITY_ROWS, 'word', 'score')} p ON p.word = x.term WHERE x.term <> t.term GROUP BY ALL)
SELECT grp, term, count(*) AS n_words, round(avg(CAST(score AS DOUBLE)), 6) AS mean_polarity FROM (SELECT * FROM m QUALIFY row_number() OVER (PARTITION BY grp, term ORDER BY n DESC, word) <= 10) GROUP BY grp, term""")
def cooccurrence_sentiment(spark, sf):
    return sentiment.by_cooccurring_word(*_sentiment_args(spark, sf))


# --- across corpora -------------------------------------------------------------------------------
LANG_COUNTS = f"(SELECT corpus, gram, count(*) AS cnt FROM {grams_sql(1, keep='doc_id, lang AS corpus')} GROUP BY corpus, gram)"


def _tops_sql(k: int) -> str:
    return f"(SELECT *, CAST(row_number() OVER (PARTITION BY corpus ORDER BY cnt DESC, gram) AS INTEGER) AS rnk FROM {LANG_COUNTS} QUALIFY rnk <= {k})"


def _lang_tops(spark: SparkSession, sf: str, k: int) -> DataFrame:
    counted = grams(_by_lang(spark, sf), 1, keep=["corpus"]).groupBy("corpus", "gram").agg(F.count("*").alias("cnt"))
    return distribution.tops(counted, k)


@register("rank_pairs", f"WITH t AS {_tops_sql(10000)}, c AS (SELECT DISTINCT corpus FROM t) SELECT a.corpus AS corpus_a, c.corpus AS corpus_b, a.gram, a.rnk AS rank_a, b.rnk AS rank_b FROM t a JOIN c ON a.corpus <> c.corpus LEFT JOIN t b ON b.corpus = c.corpus AND b.gram = a.gram WHERE a.rnk <= 1000")
def rank_pairs(spark, sf):
    return distribution.rank_pairs(_lang_tops(spark, sf, 10_000))


def _js_sql(how: str) -> str:
    return f"""SELECT corpus_a, corpus_b, round(sqrt(greatest(0.0, sum(CASE WHEN p > 0 THEN p * log2(p / ((p + q) / 2)) ELSE 0 END + CASE WHEN q > 0 THEN q * log2(q / ((p + q) / 2)) ELSE 0 END) / 2)), 6) AS distance
FROM (SELECT corpus_a, corpus_b, na / sum(na) OVER w AS p, nb / sum(nb) OVER w AS q FROM (WITH t AS {_tops_sql(1000)}, n AS (SELECT DISTINCT corpus FROM t), pr AS (SELECT a.corpus AS corpus_a, b.corpus AS corpus_b FROM n a JOIN n b ON a.corpus < b.corpus)
SELECT coalesce(l.corpus_a, r.corpus_a) AS corpus_a, coalesce(l.corpus_b, r.corpus_b) AS corpus_b, coalesce(l.cnt, 0) AS na, coalesce(r.cnt, 0) AS nb
FROM (SELECT corpus_a, corpus_b, gram, cnt FROM pr JOIN t ON t.corpus = corpus_a) l {how} JOIN (SELECT corpus_a, corpus_b, gram, cnt FROM pr JOIN t ON t.corpus = corpus_b) r
ON l.corpus_a = r.corpus_a AND l.corpus_b = r.corpus_b AND l.gram = r.gram) WINDOW w AS (PARTITION BY corpus_a, corpus_b)) GROUP BY corpus_a, corpus_b"""


@register("js_intersection", _js_sql("INNER"))
def js_intersection(spark, sf):
    return distribution.js(_lang_tops(spark, sf, 1000))


@register("js_union", _js_sql("FULL"))
def js_union(spark, sf):
    return distribution.js(_lang_tops(spark, sf, 1000), "union")


@register("js_mean", f"WITH d AS ({_js_sql('INNER')}) SELECT corpus, round(avg(distance), 6) AS mean_distance FROM (SELECT corpus_a AS corpus, distance FROM d UNION ALL SELECT corpus_b, distance FROM d) GROUP BY corpus")
def js_mean(spark, sf):
    return distribution.js_mean(js_intersection(spark, sf))


@register("shared_top_ngrams", f"SELECT gram, count(DISTINCT corpus) AS n_corpora FROM {_tops_sql(1000)} GROUP BY gram HAVING n_corpora > 1")
def shared_top_ngrams(spark, sf):
    return distribution.shared(_lang_tops(spark, sf, 1000))


def _pairs_sql(source: str, column: str) -> str:
    own = f"SELECT DISTINCT corpus, {column} AS v FROM {source} WHERE {column} IS NOT NULL"
    return f"WITH d AS ({own}), o AS (SELECT corpus, count(*) AS own FROM d GROUP BY corpus) SELECT a.corpus AS corpus_a, b.corpus AS corpus_b, count(*) AS n, round(count(*) / any_value(oa.own), 6) AS ratio_a, round(count(*) / any_value(ob.own), 6) AS ratio_b FROM d a JOIN d b ON a.v = b.v AND a.corpus < b.corpus JOIN o oa ON oa.corpus = a.corpus JOIN o ob ON ob.corpus = b.corpus GROUP BY a.corpus, b.corpus"


TEXT_PAIRS_SQL = _pairs_sql("(SELECT source AS corpus, text FROM documents)", "text")


@register("text_overlap_pairs", TEXT_PAIRS_SQL)
def text_overlap_pairs(spark, sf):
    return overlap.pairs(documents(spark, sf))


@register("url_overlap_pairs", _pairs_sql(f"(SELECT corpus, regexp_extract(url, '://([^/]+/[a-z]+)', 1) AS section FROM {PAGES})", "section"))
def url_overlap_pairs(spark, sf):
    """Sections (host and first directory) that corpora share; whole URLs of these tables are all different."""
    return overlap.pairs(pages(spark, sf).withColumn("section", F.regexp_extract("url", "://([^/]+/[a-z]+)", 1)), "section")


_SETS = "(SELECT text, list_sort(list(DISTINCT source)) AS m FROM documents WHERE text IS NOT NULL GROUP BY text HAVING count(DISTINCT source) >= 3)"


@register("overlap_sets", f"""WITH RECURSIVE e AS (SELECT text, unnest(m) AS c FROM {_SETS}),
t(text, members, last, size) AS (SELECT text, c, c, 1 FROM e UNION ALL SELECT t.text, members || '+' || e.c, e.c, size + 1 FROM t JOIN e ON e.text = t.text AND e.c > last)
SELECT members, count(*) AS n FROM t WHERE size >= 3 GROUP BY members ORDER BY n DESC, members LIMIT 10""")
def overlap_sets(spark, sf):
    return overlap.subsets(documents(spark, sf))


@register("overlap_sets_exclusive", f"SELECT array_to_string(m, '+') AS members, count(*) AS n FROM {_SETS} GROUP BY ALL ORDER BY n DESC, members LIMIT 10")
def overlap_sets_exclusive(spark, sf):
    return overlap.subsets(documents(spark, sf), exclusive=True)


@register("share_originating", f"WITH p AS ({TEXT_PAIRS_SQL}) SELECT corpus_a, corpus_b, ratio_a AS share FROM p UNION ALL SELECT corpus_b, corpus_a, ratio_b FROM p")
def share_originating(spark, sf):
    return overlap.containment(text_overlap_pairs(spark, sf))


# --- curation -------------------------------------------------------------------------------------
@register("filtered_corpus", f"SELECT min(doc_id) AS doc_id FROM {DOCS} WHERE NOT ({BLANK}) GROUP BY text")
def filtered_corpus(spark, sf):
    return curate.apply(documents(spark, sf), ["duplicates", "blank"]).select("doc_id")


def _long_sql(name: str, metrics: list[str], sql: str | None = None, label: str | None = None, corpus: str = "corpus") -> str:
    """One analysis of the card: its query's SQL by name if none is given; ``label`` is the column that tells rows of a corpus apart."""
    of = f" || ' ' || {label}" if label else ""
    return " UNION ALL ".join(f"SELECT {corpus} AS corpus, '{name}' AS analysis, '{m}'{of} AS metric, round(CAST({m} AS DOUBLE), 6) AS value FROM ({sql or ORACLES[name]})" for m in metrics)


CARD_SQL = [
    _long_sql("summary_stats", ["n_docs", "n_bytes", "n_chars", "n_tokens", "max_tokens", "min_tokens", "n_blank", "mean_tokens"]),
    _long_sql("text_duplicates", ["n_docs", "dup_docs", "doc_ratio", "dup_clusters", "cluster_ratio", "surplus"]),
    _long_sql("length_medians", ["median_tokens", "median_chars"]),
    _long_sql("distinct_ngrams_exact", ["n_distinct", "share_of_tokens"]),
    _long_sql("language_share", ["n", "share"], label="lang"),
    _long_sql("contamination_rate", ["n_items", "n_hit", "rate"]),
    _long_sql("pii_counts", ["n"], label="kind"),
    _long_sql("toxic_documents", ["n_docs", "n_toxic", "pct"]),
    _long_sql("share_originating", ["share"], label="corpus_b", corpus="corpus_a"),
]


@register("audit_card", " UNION ALL ".join(CARD_SQL))
def audit_card(spark, sf):
    """The analyses of ``documents`` that have figures for each corpus."""
    plain = ["summary_stats", "text_duplicates", "length_medians", "distinct_ngrams_exact", "contamination_rate", "toxic_documents"]
    results = {name: QUERIES[name](spark, sf) for name in [*plain, "language_share", "pii_counts"]}
    results["share_originating"] = share_originating(spark, sf).withColumnRenamed("corpus_a", "corpus")
    return curate.card(results, labels={"language_share": "lang", "pii_counts": "kind", "share_originating": "corpus_b"})
