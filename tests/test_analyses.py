"""Worked examples of the analyses."""

import collections
import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from corpus_audit.analyses import contamination, curate, dates, distribution, domains, duplicates, geo, lengths, overlap, pii, sentiment, toxicity
from corpus_audit.search import index, query
from tests.test_counting import corpus


def pages(spark, urls):
    return corpus(spark, ["x y"] * len(urls)).withColumn("url", F.element_at(F.array(*[F.lit(u) for u in urls]), (F.col("doc_id") + 1).cast("int")))


URLS = ["http://A.com/x", "https://a.com:8080/y", "https://b.co.uk/", None, "UNLIKELY", "http://A.com/x"]


def test_urls(spark):
    df = pages(spark, URLS)
    assert {r["host"]: (r["n"], r["share"]) for r in domains.hosts(df).collect()} == {"a.com": (3, 0.75), "b.co.uk": (1, 0.25)}
    assert {r["scheme"]: r["n"] for r in domains.schemes(df).collect()} == {"http": 2, "https": 2}
    assert {r["suffix"]: r["n"] for r in domains.suffixes(df, ["com", "co.uk", "uk"]).collect()} == {"com": 3, "co.uk": 1}
    row = duplicates.stats(df, "url").first()
    assert (row["n_docs"], row["dup_docs"], row["dup_clusters"], row["surplus"]) == (5, 2, 1, 1)


def test_duplicate_ratios_replay_printed_totals():
    # documents, documents in clusters, clusters -> the two printed ratios
    for docs, dup, clusters, doc_ratio, cluster_ratio in ((431_584_362, 164_740_386, 19_934_531, 0.38, 0.07), (210_607_728, 138_716_558, 64_623_824, 0.66, 0.47), (930_453_833, 459_530_754, 218_875_070, 0.49, 0.32)):
        assert round(dup / docs, 2) == doc_ratio
        assert round(clusters / (docs - dup + clusters), 2) == cluster_ratio


EMAIL = [("mail me at ann.b@mail.example.org now", ["ann.b@mail.example.org"]), ("( (@x.org y", []), ("joe@localhost here", []), ("end joe@mail.org", []), ("see joe@mail.org, ok", ["joe@mail.org"])]


@pytest.mark.parametrize("text, want", EMAIL)
def test_email(spark, text, want):
    assert [r["value"] for r in pii.find(corpus(spark, [text]), "email").collect()] == want


def test_email_at_end(spark):
    assert pii.find(corpus(spark, ["end joe@mail.org"]), "email", at_end=True).count() == 1


PHONE = [
    ("call (555) 123-4567 now", 1), ("call 555.123.4567", 1), ("id 5551234567890", 1), ("ISBN " + "x" * 20 + " 555 123 4567", 0), ("ISBN " + "x" * 60 + " 555 123 4567", 1),
    ("# 555 123 4567", 0), ("go http://x.org/5551234567 or 5551234567", 0), ("123 4567", 0),
]


@pytest.mark.parametrize("text, n", PHONE)
def test_phone(spark, text, n):
    assert pii.find(corpus(spark, [text]), "phone").count() == n


def test_phone_closed_boundary(spark):
    assert pii.find(corpus(spark, ["id 5551234567890"]), "phone", boundary="closed").count() == 0


def test_ip(spark):
    assert [r["value"] for r in pii.find(corpus(spark, ["at 10.0.0.255 and 1.2.3"]), "ip").collect()] == ["10.0.0.255"]
    assert pii.find(corpus(spark, ["doi 10.0.0.1"]), "ip").count() == 0


def test_prefilter(spark):
    assert [r["doc_id"] for r in pii.prefilter(corpus(spark, ["ok", "-" * 50, "-" * 51])).collect()] == [0, 1]


def items(spark):
    return spark.createDataFrame([(1, ["red fox", "blue bird"]), (2, ["only here"]), (3, ["split one", "split two"])], "item_id long, fields array<string>")


@pytest.mark.parametrize("method", ["scan", "index"])
def test_contamination(spark, method):
    docs = corpus(spark, ["a blue bird and a red fox", "split one alone", "split two alone", "only here"])
    pairs = {(r["doc_id"], r["item_id"]) for r in contamination.evaluate(docs, items(spark), method).collect()}
    assert pairs == {(0, 1), (3, 2)}
    loose = {(r["doc_id"], r["item_id"]) for r in contamination.evaluate(docs, items(spark), method, "any").collect()}
    assert loose == {(0, 1), (1, 3), (2, 3), (3, 2)}
    clean = contamination.remove(docs, contamination.evaluate(docs, items(spark)))
    assert contamination.evaluate(clean, items(spark)).count() == 0
    assert contamination.eligible(items(spark)).count() == 2


def three(spark):
    rows = [("A", "t"), ("B", "t"), ("C", "t"), ("A", "u"), ("B", "u"), ("A", "v"), ("A", "v")]
    return spark.createDataFrame([(i, c, t) for i, (c, t) in enumerate(rows)], "doc_id long, corpus string, text string")


def test_overlap_sets_have_no_upper_size(spark):
    rng = random.Random(3)
    held = [rng.sample([f"c{i}" for i in range(12)], rng.randrange(1, 9)) for _ in range(40)] + [[f"c{i}" for i in range(7)]] * 30
    docs = spark.createDataFrame([(i, c, f"text {i}") for i, own in enumerate(held) for c in own], "doc_id long, corpus string, text string")
    counts = collections.Counter("+".join(s) for own in held for k in range(3, len(own) + 1) for s in itertools.combinations(sorted(own), k))
    for k in (10, 100):
        want = sorted(counts.items(), key=lambda x: (-x[1], x[0]))[:k]
        assert [(r["members"], r["n"]) for r in overlap.subsets(docs, k=k).collect()] == want
    assert any(name.count("+") >= 4 for name, _ in want)


def test_overlap_is_inclusive(spark):
    got = {(r["corpus_a"], r["corpus_b"]): (r["n"], r["ratio_a"], r["ratio_b"]) for r in overlap.pairs(three(spark)).collect()}
    assert got == {("A", "B"): (2, round(2 / 3, 6), 1.0), ("A", "C"): (1, round(1 / 3, 6), 1.0), ("B", "C"): (1, 0.5, 1.0)}
    assert {r["members"]: r["n"] for r in overlap.subsets(three(spark), min_size=2).collect()} == {"A+B": 2, "A+C": 1, "B+C": 1, "A+B+C": 1}
    assert {r["members"]: r["n"] for r in overlap.subsets(three(spark), min_size=2, exclusive=True).collect()} == {"A+B": 1, "A+B+C": 1}


@pytest.mark.parametrize("a, b, inner, union", [("x y", "x y", 0.0, 0.0), ("x", "y", None, 1.0), ("x y", "y z", 0.0, round(math.sqrt(0.5), 6))])
def test_js(spark, a, b, inner, union):
    counted = spark.createDataFrame([("A", g, 1) for g in a.split()] + [("B", g, 1) for g in b.split()], "corpus string, gram string, cnt long")
    top = distribution.tops(counted, 10)
    assert distribution.js(top).first()["distance"] == inner
    assert distribution.js(top, "union").first()["distance"] == union


def test_sentences_and_classifier_units(spark):
    df = corpus(spark, ["Fine day. You moron!\nNext"])
    assert df.select(toxicity.sentences("text")).first()[0] == ["Fine day.", "You moron!", "Next"]


def test_lexicon_counts_two_word_terms(spark):
    lex = spark.createDataFrame([("bad", "x"), ("very bad", "y")], "term string, category string")
    assert {r["category"]: r["n"] for r in toxicity.matches(corpus(spark, ["Very bad, BAD"]), lex).collect()} == {"x": 2, "y": 1}


def test_sentiment(spark):
    terms = spark.createDataFrame([("g", "he")], "grp string, term string")
    polar = spark.createDataFrame([("best", 1.0), ("trash", -0.8)], "term string, score double")
    row = sentiment.by_term(corpus(spark, ["He is best. He is here. She is trash."]), terms, polar).first()
    assert (row["n_sentences"], row["mean_polarity"]) == (2, 0.5)


def test_lengths(spark):
    df = corpus(spark, ["x" * n for n in (3, 3, 3, 3, 3, 5, 9)])
    assert [(r["length"], r["n"]) for r in lengths.outliers(lengths.histogram(df), ratio=20).collect()] == [(3, 5)]
    assert lengths.medians(df).first()["median_chars"] == 3


def test_search_agrees_with_text(spark):
    idx = index.build(corpus(spark, ["a b c a b", "b a", "c"]))
    got = {r["phrase"]: (r["df"], r["tf"]) for r in query.frequency(idx, [["a", "b"], ["b"], ["z"]]).collect()}
    assert got == {"a b": (1, 2), "b": (2, 3), "z": (0, 0)}
    assert [r[0] for r in query.run(idx, query.Not(query.Term("a"))).collect()] == [2]
    assert [r[0] for r in query.run(idx, query.And((query.Term("b"), query.Not(query.Phrase(("a", "b")))))).collect()] == [1]


def test_index_in_a_bucketed_table(spark):
    index.save(index.build(corpus(spark, ["a b", "b"])), "toy_index", 4)
    assert query.ngram_counts(index.load(spark, "toy_index"), "a b").first()["df"] == 1
    spark.sql("DROP TABLE toy_index")


def test_geo(spark):
    ranges = spark.createDataFrame([(10 << 24, (10 << 24) + 255, "X")], "lo long, hi long, country string")
    got = {r["ip"]: r["country"] for r in geo.locate(spark.createDataFrame([("10.0.0.7",), ("10.0.1.0",)], "ip string"), ranges).collect()}
    assert got == {"10.0.0.7": "X", "10.0.1.0": None}


def test_estimated_dates_are_lower_bounds(spark):
    df = spark.createDataFrame([(1, "c", "2005-01-01"), (2, "c", "2006-01-01")], "key long, corpus string, t string").withColumn("created", F.to_timestamp("t"))
    seen = spark.createDataFrame([(1, "2003-05-05"), (1, "2004-01-01")], "key long, s string").withColumn("first_seen", F.to_timestamp("s"))
    assert {r["yr"]: r["n"] for r in dates.by_year_estimated(df, seen, "key").collect()} == {2003: 1, 2006: 1}


def test_curation(spark):
    df = corpus(spark, ["a", "a", " ", "=" * 12])
    assert [r["doc_id"] for r in curate.apply(df, ["duplicates", "blank", "repeats"]).collect()] == [0]


def test_index_route_agrees_with_the_scan_on_fields_cut_anywhere(spark):
    import random

    rng = random.Random(11)
    parts = ["3.5", "it's", "good", "now", "ok", "a.b", "1,000", "x", "_y", "'", ".", "end.", "né", "10"]
    texts = ["price is 3.5 good now ok here", *(" ".join(rng.choice(parts) for _ in range(30)) for _ in range(40))]
    fields = [".5 good now ok"]
    for t in texts[1:]:
        for _ in range(5):
            a = rng.randrange(len(t) - 25)
            fields.append(t[a : a + rng.randrange(3, 60)].strip() or "x")
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    asked = spark.createDataFrame([(i, 0, f) for i, f in enumerate(fields)], "item_id long, field int, value string")
    want = {(d, i) for d, t in enumerate(texts) for i, f in enumerate(fields) if f in t}
    for route in (contamination.hits_by_index, contamination.hits_by_scan):
        assert {(r["doc_id"], r["item_id"]) for r in route(docs, asked).collect()} == want


def test_scan_deals_many_fields_to_several_automata(spark, monkeypatch):
    monkeypatch.setattr(contamination, "MAX_FIELDS", 3)
    docs = spark.createDataFrame([(1, "a b c d e f g h")], "doc_id long, text string")
    asked = spark.createDataFrame([(i, 0, f) for i, f in enumerate("abcdefghz")], "item_id long, field int, value string")
    assert {r["item_id"] for r in contamination.hits_by_scan(docs, asked).collect()} == set(range(8))


def test_classifier_scores_sentences_within_the_row(spark):
    rows = [(1, "Fine day. You moron! Next"), (2, "Fine day."), (3, None), (4, "")]
    out = {r["doc_id"]: (r["toxic"], r["score"]) for r in toxicity.classify(spark.createDataFrame(rows, "doc_id long, text string"), {"": -1.0, "moron": 3.0, "fine": -0.5}).collect()}
    assert out[1] == (1, 2.0) and out[2] == (0, -1.5) and out[3][0] == out[4][0] == 0


def test_card(spark):
    plain = spark.createDataFrame([("a", 3, 0.5), ("b", 1, None)], "corpus string, n_docs long, ratio double")
    labelled = spark.createDataFrame([("a", "en", 2), ("a", "fr", 1), (None, "en", 1)], "corpus string, lang string, n long")
    found = {(r["corpus"], r["analysis"], r["metric"]): r["value"] for r in curate.card({"s": plain, "l": labelled}, labels={"l": "lang"}).collect()}
    assert found == {("a", "s", "n_docs"): 3, ("a", "s", "ratio"): 0.5, ("b", "s", "n_docs"): 1, ("b", "s", "ratio"): None, ("a", "l", "n en"): 2, ("a", "l", "n fr"): 1, (None, "l", "n en"): 1}
