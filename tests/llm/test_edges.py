"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns, for every operator and stage."""

import re

import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

import corpus_pipeline
from corpus_audit.llm import extraction, language, line_dedup, media, mixing, near_dup, packing, quality, sharding, toxicity

DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())])
LONG = " ".join(f"word{i % 977} and{i % 13}" for i in range(15_000))
CLEAN = "One morning the quiet river carried small boats past the old stone bridge while children counted them and waved at every captain who passed below their feet."
ROWS = [
    (1, CLEAN, "en", "a", 1), (2, CLEAN, "en", "a", 1), (2, CLEAN, "en", "a", 1), (None, CLEAN, "en", "b", 1), (3, None, None, None, None), (4, "", "en", "a", 0), (5, " \n\t\n ", "en", "a", 5),
    (6, LONG, "fr", "b", 9), (7, "短い文 Ünï ﷽ \U0001f600", "de", None, 3), (8, "x\n" * 50, None, "a", 100), (None, None, None, None, None), (9, "\x00\x1f�", "en", "a", 3),
]


@pytest.fixture(scope="module")
def docs(spark):
    clash = ["host_key", "n_words", "shard", "ord", "drop", "node", "component", "score", "u", "p", "rate", "h1", "piece", "n_lines", "__x"]
    return spark.createDataFrame(ROWS, DOCS).withColumns({c: F.lit("other") for c in clash})


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (1, 1, 1), (6, 0, 1), (None, 1, 1), (7, None, None), (99, 1, 0), (2, 1, 0)], "doc_id long, quality int, toxic int")


def empty(docs):
    return docs.limit(0)


def test_quality(spark, docs):
    out = quality.judged(near(quality.measures(docs, ["doc_id", "source"]))).collect()
    assert len(out) == len(ROWS)
    by = {(r["doc_id"], r["n_words"]): r for r in out}
    assert by[(3, 0)]["base_failed"] and by[(4, 0)]["base_failed"] and not by[(1, 27)]["base_failed"]
    assert by[(8, 50)]["n_repeat_words"] == 50 and by[(8, 50)]["n_dup_lines"] == 49
    assert quality.judged(near(quality.measures(empty(docs), ["doc_id", "source"]))).count() == 0


def near(df):
    from corpus_audit.llm.common import materialize

    return materialize(df, "test")


def test_near_duplicates(spark, docs):
    out = near_dup.near_duplicates(spark, docs).collect()
    assert len(out) == len(ROWS)
    component = {(r["doc_id"], r["n_shingles"]): r["component_id"] for r in out}
    assert component[(1, 23)] == component[(2, 23)] == 1 and component[(None, 23)] is None
    assert component[(3, 0)] == 3 and component[(5, 0)] == 5 and component[(4, 0)] == 4
    assert near_dup.near_duplicates(spark, empty(docs)).count() == 0


def test_line_dedup(spark, docs):
    out = line_dedup.deduplicate_lines(docs).select("doc_id", "text", "n_lines", "n_removed_lines").collect()
    assert len(out) == len(ROWS)
    texts = {}
    for r in out:
        texts.setdefault(r["doc_id"], []).append(r["text"])
    assert texts[1] == [CLEAN] and texts[2] == ["", ""] and sorted(texts[None], key=str) == ["", None]
    assert texts[3] == [None] and texts[5] == [" \n\t\n "] and texts[6] == [LONG]
    assert line_dedup.deduplicate_lines(empty(docs)).count() == 0


def test_sharding(spark, docs, tmp_path):
    out = sharding.shard_sizes(sharding.sizes(docs)).collect()
    assert len(out) == len(ROWS) and sum(r["size"] for r in out) == sum(len((r[1] or "").encode()) + 1 for r in ROWS)
    for k in range(8):
        assert sorted(r["slot"] for r in out if r["shard"] == k) == list(range(sum(r["shard"] == k for r in out)))
    assert sharding.shard_sizes(sharding.sizes(empty(docs))).count() == 0
    sharding.write_shards(docs, f"{tmp_path}/shards")
    assert spark.read.parquet(f"{tmp_path}/shards").count() == len(ROWS)


def test_media(spark, docs):
    files = media.mux(docs)
    assert files.count() == len(ROWS)
    back = media.demux(files.filter("doc_id = 6"), "doc_id").collect()
    assert back and all(r["end_s"] > r["start_s"] for r in back)
    assert media.demux(media.mux(empty(docs))).count() == 0


def test_language(spark, docs):
    model = language.learn(docs)
    out = {r["doc_id"]: r for r in language.identify(docs, model).collect()}
    assert out[3]["lang_pred"] == out[5]["lang_pred"] == out[9]["lang_pred"] == "und" and out[1]["lang_pred"] in ("en", "fr", "de")
    none = language.learn(empty(docs))
    assert {r["lang_pred"] for r in language.identify(docs, none).collect()} == {"und"}
    assert language.identify(empty(docs), model).count() == 0


def test_toxicity(spark, docs, labels):
    net = toxicity.learn(docs, labels)
    out = toxicity.score(docs, net).collect()
    assert len(out) == len(ROWS) and all(0 <= r["score"] <= 1 for r in out)
    assert {r["score"] for r in out if r["doc_id"] in (3, 4, 5)} == {0.0}
    blank = toxicity.learn(empty(docs), labels.limit(0))
    assert toxicity.score(empty(docs), blank).count() == 0


def test_mixing(spark, docs, labels):
    out, domains, _ = mixing.mixed(spark, docs, labels)
    rows = out.collect()
    assert len(rows) == len(ROWS) and all(abs(sum(r["p"]) - 1) < 1e-9 and r["rate"] >= 0 for r in rows)
    assert mixing.mixed(spark, docs, labels.limit(0))[1] == ["all"]
    assert mixing.mixed(spark, empty(docs), labels)[0].count() == 0


def test_packing(spark, docs):
    out = packing.pack(spark, docs).collect()
    whole = {}
    for r in out:
        whole[r["doc_id"]] = whole.get(r["doc_id"], 0) + (r["piece"] == 0)
    assert whole[2] == 2 and whole[None] == 2 and whole[3] == 1 and sum(whole.values()) == len(ROWS)
    assert packing.pack(spark, empty(docs)).count() == 0


def test_extraction(spark):
    rows = [(1, "http://a.org/x", "<p>a &amp; b</p>"), (1, "http://a.org/x", "<p>a &amp; b</p>"), (None, None, None), (2, "not a url", ""), (3, "http://a.org/" + "y" * 5000, "<div" + "<" * 2000), (4, "http://a.org/z", "<p>" * 500 + "deep")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"host": F.lit(1), "pid": F.lit(2), "text": F.lit("t"), "gone": F.lit(0)})
    out = extraction.extract(pages).collect()
    assert len(out) == len(rows) and {r["text"] for r in out if r["page_id"] == 1} == {"a & b"} and all(r["n_chars"] == len(r["text"]) for r in out)
    assert extraction.extract(pages.limit(0)).count() == 0


def test_stages_on_odd_rows(spark, docs, sf):
    more = [(100 + i, CLEAN.replace("quiet", f"quiet{i} grey{i}").replace("boats", f"boats{i} and rafts{i}").replace("bridge", f"bridge{i}"), "en", ("a", "b")[i % 2], 1) for i in range(40)]
    df = docs.unionByName(spark.createDataFrame(more, DOCS), allowMissingColumns=True)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = near(stage(spark, df, sf))
        assert out.columns == docs.columns, name
        df = out
    assert corpus_pipeline.STAGES[-1][1](spark, df, sf).count() >= 1
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty(docs), sf).count() == 0, name


def test_guard_is_in_the_entry_alone():
    import __spark_entry__ as entry

    assert {"pipeline", *(f"op{n}" for n in range(1, 11))} <= {re.sub(r"^(op\d+)_.*", r"\1", k) for k in entry.queries()}
