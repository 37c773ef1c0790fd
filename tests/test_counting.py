"""Hand counts and invariants of the counting methods on toy corpora."""

import random

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st
from pyspark.sql import Window
from pyspark.sql import functions as F

from corpus_audit.analyses import ngrams, stats
from corpus_audit.counting import accuracy, narrow
from corpus_audit.counting.exact import tally, top
from corpus_audit.counting.hashed import U32_MAX, HashSpec, cell_counts, occupancy
from corpus_audit.sources.io import CORE_SCHEMA
from corpus_audit.text import ngrams as text_ngrams
from corpus_audit.text.ngrams import grams
from corpus_audit.text.tokenize import tokens


def corpus(spark, texts, name="toy"):
    return spark.createDataFrame([(i, name, None, t, None, None, "en") for i, t in enumerate(texts)], CORE_SCHEMA)


def found(df):
    return {r["gram"]: r[-1] for r in df.collect()}


TOY = ["", "  \n ", "one", "a " * 12, "b c d", "b c d"]


def test_toy_counts(spark):
    row = stats.summary(corpus(spark, TOY)).first()
    assert (row["n_docs"], row["n_tokens"], row["max_tokens"], row["min_tokens"], row["n_blank"]) == (6, 19, 12, 0, 2)
    assert found(ngrams.top_exact(corpus(spark, TOY), 1, 2)) == {"a": 12, "b": 2}
    assert found(ngrams.top_exact(corpus(spark, TOY), 3, 5)) == {"a a a": 10, "b c d": 2}
    assert ngrams.top_exact(corpus(spark, TOY), 13, 5).count() == 0


def test_null_and_empty(spark):
    df = corpus(spark, [None])
    assert stats.summary(df).first()["n_tokens"] == 0
    assert ngrams.top_exact(df.limit(0), 1, 5).count() == 0


@pytest.mark.parametrize("text, want", [("cdn.shopify.com don't 3.14 T-Shirt", ["cdn.shopify.com", "don't", "3.14", "T", "-", "Shirt"]), ("e.g. x", ["e.g", ".", "x"]), ("a b", ["a", "b"]), ("", [])])
def test_tokens(spark, text, want):
    assert spark.createDataFrame([(text,)], "text string").select(tokens("text")).first()[0] == want


def test_collisions_only_add(spark):
    df = spark.createDataFrame([(g,) for g in "aab" * 5 + "cdefgh"], "gram string")
    tight = HashSpec(2, fn="md5_prefix")
    assert accuracy.bound_check(df, "gram", tight).count() == 0
    report = accuracy.error_report(df, "gram", tight).first()
    assert report["n_grams"] == 8 and report["n_inflated"] > 0
    assert cell_counts(df, "gram", tight).agg(F.sum("cnt")).first()[0] == df.count()


def test_u32_saturates(spark):
    cells = spark.createDataFrame([(1, U32_MAX - 1), (2, U32_MAX + 3)], "cell long, cnt long")
    assert [r[0] for r in cells.select(F.least("cnt", F.lit(U32_MAX))).collect()] == [U32_MAX - 1, U32_MAX]
    assert not cell_counts(spark.createDataFrame([("x",)], "gram string"), "gram", HashSpec(4, counter="u32")).first()["saturated"]


def test_full_table_is_flagged(spark):
    row = occupancy(spark.range(100).select(F.col("id").cast("string").alias("gram")), "gram", HashSpec(8)).first()
    assert (row["set_cells"], row["nearly_full"], row["linear_est"]) == (8, True, None)


def test_linear_estimate_is_closer(spark):
    df = spark.range(40_000).select(F.col("id").cast("string").alias("gram"))
    row = occupancy(df, "gram", HashSpec(65_536)).first()
    assert row["set_cells"] <= 40_000
    assert abs(row["linear_est"] - 40_000) < abs(row["set_cells"] - 40_000)


def test_budget():
    assert HashSpec.for_budget(800).m == 100
    assert HashSpec.for_budget(800, "u32").m == 200
    assert HashSpec.for_budget(100, "bool").m == 800


@pytest.mark.parametrize("m", [4, 64, 4096])
def test_certified_equals_exact(spark, m):
    texts = [" ".join(f"w{k}" for k in range(n)) for n in (1, 2, 3, 5, 9, 20, 40)] * 3
    df = corpus(spark, texts)
    out = ngrams.top_certified(df, 1, 3, HashSpec(m))
    if out.first()["certified"]:
        assert found(out.select("gram", "cnt")) == found(ngrams.top_exact(df, 1, 3))
    if m == 4096:
        assert out.first()["certified"]


def test_no_collisions_makes_hashed_exact(spark):
    df = corpus(spark, ["a b c a b a", "c d d"])
    wide = HashSpec(2**40)
    assert found(ngrams.top_hashed(df, 1, 3, wide)) == found(ngrams.top_exact(df, 1, 3))
    assert found(ngrams.bottom_hashed(df, 1, 2, wide)) == found(ngrams.bottom_exact(df, 1, 2))


@settings(max_examples=8, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.lists(st.integers(0, 3), min_size=0, max_size=60), st.integers(1, 5), st.integers(5, 9))
def test_chunked_ngrams_are_the_same(spark, words, n, size):
    df = spark.createDataFrame([(1, [f"w{w}" for w in words])], "doc_id int, tokens array<string>")
    cut = text_ngrams.chunked(df, n, size=size).select(F.explode(text_ngrams.windows("tokens", n)).alias("w")).collect()
    want = [[f"w{w}" for w in words[i : i + n]] for i in range(len(words) - n + 1)]
    assert sorted(r["w"] for r in cut) == sorted(want)


def test_seeds_agree(spark):
    assert accuracy.seed_agreement(corpus(spark, TOY), "text").count() == 0


def test_long_grams_are_counted_by_keys(spark, tmp_path, monkeypatch):
    """Null and small corpora, ties in several runs, shared keys and long texts, against counts of the strings; no string of a rare window is shuffled."""
    rng = random.Random(5)
    passages = [" ".join(rng.choice("abcdéz") + str(rng.randrange(9)) for _ in range(40)) for _ in range(60)]
    rows = [(i, rng.choice(["x", "y", None]), "\x01 ".join(rng.choices(passages, k=rng.randrange(6)))) for i in range(300)]
    rows += [(1000, "alone", "a b c d e f g h i j k l"), (1001, "short", "a b"), (1002, "y", None), (1003, "alone", "b c d e f g h i j k a a")]
    df = spark.createDataFrame(rows, "doc_id long, corpus string, text string").repartition(3)
    monkeypatch.setattr(narrow, "TIED_KEYS", 700)
    for n, k, widths in ((10, 900, (narrow.KEY_BITS, 9)), (10, 100_000, (narrow.KEY_BITS,)), (100, 5, (narrow.KEY_BITS,))):
        counted = tally(grams(df, n, keep=["corpus"]), ["corpus", "gram"]).withColumn("rnk", F.row_number().over(Window.partitionBy("corpus").orderBy(F.desc("cnt"), "gram"))).filter(F.col("rnk") <= k)
        want = sorted(map(tuple, counted.collect()), key=repr)
        for bits in widths:
            assert sorted(map(tuple, narrow.top(df, n, k, bits).collect()), key=repr) == want and want
    plan = ngrams.top_by_corpus(df, 10, 5)._jdf.queryExecution().optimizedPlan().toString()
    assert "array_join" not in plan, "strings of all windows are grouped"


def test_longest_grams_are_not_grouped_as_strings(spark):
    texts = [" ".join(f"w{i % 7}" for i in range(230)), "b " * 120, "", None]
    df = corpus(spark, texts)
    got = ngrams.top_exact(df, 100, 8)
    assert [tuple(r) for r in got.collect()] == [tuple(r) for r in top(tally(grams(df, 100), ["gram"]), 8).collect()]
    assert "array_join" not in got._jdf.queryExecution().optimizedPlan().toString(), "strings of all windows are grouped"
