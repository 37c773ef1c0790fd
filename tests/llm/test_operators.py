"""Operators against brute force, exact round trips, SQL and held-out accuracy."""

import collections
import html
import os
import random
import re
import zlib

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from corpus_audit.llm import extraction, graph, kernels, language, line_dedup, media, mixing, near_dup, packing, quality, sharding, toxicity

WORD = re.compile("[^\x20\x09-\x0d]+")
FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@pytest.fixture(scope="module")
def texts(spark, sf):
    return {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    return con


def buffer(*texts):
    return kernels.text_buffer(pa.array(list(texts), type=pa.string()))


def shingles(text):
    words = WORD.findall((text or "").translate(FOLD))
    return {tuple(words[i : i + 5]) for i in range(len(words) - 4)} if len(words) >= 5 else {tuple(words)} if words else set()


# --- kernels ----------------------------------------------------------------------------------
@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet="aBé \n\t\x0b漢.", max_size=30), min_size=1, max_size=6))
def test_words_are_cut_and_hashed_by_value(rows):
    data, off = buffer(*rows)
    by_hash = {}
    for words in (kernels.Words(data, off, True), kernels.Words.whole(data, off, True)):
        for i, row in enumerate(rows):
            found = [bytes(data[a:b]).decode() for a, b in zip(words.start[words.first[i] : words.first[i + 1]], words.end[words.first[i] : words.first[i + 1]], strict=True)]
            assert found == WORD.findall(row)
            for w, h in zip(found, words.hash[words.first[i] : words.first[i + 1]], strict=True):
                assert by_hash.setdefault(int(h), w.translate(FOLD)) == w.translate(FOLD)


# --- near duplicates ----------------------------------------------------------------------------
def components(links, nodes):
    parent = {n: n for n in nodes}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        parent[b] = a
    return {n: find(n) for n in nodes}


def test_near_duplicates_equal_brute_force(spark, texts):
    base = next(t for t in texts.values() if 150 < len(t.split()) < 400).split()
    rng, extra = random.Random(5), dict(texts)
    for k in range(60):  # a cloud of copies around one text, from very near to too far
        words = list(base)
        for _ in range(rng.randint(0, 14)):
            words[rng.randrange(len(words))] = f"new{rng.randrange(10**6)}"
        extra[10_000 + k] = " ".join(words)
    sets = {i: shingles(t) for i, t in extra.items()}
    held = collections.defaultdict(list)
    for i, s in sets.items():
        for g in s:
            held[g].append(i)
    links = []
    for i, s in sets.items():
        for j, both in collections.Counter(j for g in s for j in held[g] if j < i).items():
            if 100 * both >= 75 * (len(s) + len(sets[j]) - both):
                links.append((i, j))
    want = components(links, sets)
    out = near_dup.near_duplicates(spark, spark.createDataFrame(list(extra.items()), "doc_id long, text string")).collect()
    assert {r["doc_id"]: r["component_id"] for r in out} == want
    assert all(r["n_shingles"] == len(sets[r["doc_id"]]) and r["kept"] == (r["doc_id"] == r["component_id"]) for r in out)


def test_pairs_within_the_distance_share_a_key():
    rng = np.random.default_rng(1)
    for _ in range(200):
        a = rng.integers(0, 2**16, near_dup.INDEXED, dtype=np.uint16)
        b = a.copy()
        b[rng.choice(near_dup.INDEXED, near_dup.DISTANCE, replace=False)] ^= 1
        lanes = np.stack([a, b]).view(np.int64)
        batch = pa.RecordBatch.from_arrays([pa.array([1, 2]), *(pa.array(lanes[:, i].copy()) for i in range(near_dup.INDEX_LANES))], names=["node", *near_dup.LANES[: near_dup.INDEX_LANES]])
        (out,) = near_dup._index(iter([batch]))
        keys = collections.defaultdict(set)
        for k, n in zip(out["key"].to_pylist(), out["node"].to_pylist(), strict=True):
            keys[n].add(k)
        assert keys[1] & keys[2]


def test_components_of_long_chains(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (100, 100)]
    out = dict(graph.connected_components(spark.createDataFrame(edges, "u long, v long")).collect())
    assert out == {**dict.fromkeys(range(41), 0), 100: 100, 101: 100}


# --- line dedup ------------------------------------------------------------------------------------
def test_line_dedup_equals_brute_force(spark, texts):
    lines = {i: [(n, tuple(WORD.findall(x))) for n, x in enumerate(t.split("\n")) if WORD.search(x)] for i, t in texts.items()}
    hashes = {w: int(line_dedup.line_arrays(kernels.Words(*buffer(" ".join(w)), False), *buffer(" ".join(w)))[1][0]) for v in lines.values() for _, w in v}
    marks = {i: line_dedup.winnow(np.array([hashes[w] for _, w in v], dtype=np.int64), np.array([len(w) for _, w in v])) for i, v in lines.items()}
    first = {}
    for i in sorted(lines):
        for p in marks[i]:
            first.setdefault(lines[i][p][1], (i, p))
    out = {r["doc_id"]: r for r in line_dedup.deduplicate_lines(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    for i, own in lines.items():
        drop = set()
        for p in marks[i]:
            j, q = first[own[p][1]]
            if (j, q) == (i, p):
                continue
            a = b = 0
            while p - a > 0 and q - a > 0 and own[p - a - 1][1] == lines[j][q - a - 1][1]:
                a += 1
            while p + b + 1 < len(own) and q + b + 1 < len(lines[j]) and own[p + b + 1][1] == lines[j][q + b + 1][1]:
                b += 1
            run = own[p - a : p + b + 1]
            if sum(len(w) for _, w in run) >= line_dedup.MIN_WORDS:
                drop |= {n for n, _ in run}
        assert out[i]["text"] == "\n".join(x for n, x in enumerate(texts[i].split("\n")) if n not in drop)
        assert out[i]["n_removed_lines"] == len(drop)


def test_planted_passage_goes_from_later_documents(spark):
    passage = " ".join(f"passage{i}" for i in range(60))
    rows = [(i, f"own line {i} here\n{passage}\nend {i}") for i in range(5)]
    out = {r["doc_id"]: r["text"] for r in line_dedup.deduplicate_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert passage in out[0] and all(out[i] == f"own line {i} here\nend {i}" for i in range(1, 5))


def by_all_earlier_places(texts):
    """The texts without every line in a run of enough words that equals a run at any earlier place."""
    lines = {i: [(n, tuple(WORD.findall(x))) for n, x in enumerate(t.split("\n")) if WORD.search(x)] for i, t in texts.items()}
    out = {}
    for i, own in sorted(lines.items()):
        drop = set()
        for j, other in lines.items():
            if j > i:
                continue
            for shift in range(1 if i == j else 1 - len(other), len(own)):  # line p of own against line p - shift of other
                run = []
                for p in range(max(0, shift), min(len(own), len(other) + shift) + 1):
                    if p < min(len(own), len(other) + shift) and own[p][1] == other[p - shift][1]:
                        run.append(own[p])
                        continue
                    if sum(len(w) for _, w in run) >= line_dedup.MIN_WORDS:
                        drop |= {n for n, _ in run}
                    run = []
        out[i] = ("\n".join(x for n, x in enumerate(texts[i].split("\n")) if n not in drop), len(drop))
    return out


def test_line_dedup_holds_each_run_against_all_earlier_places(spark):
    said = lambda who, n: " ".join(f"{who}{k}" for k in range(n))
    texts = {}
    for c in range(12):  # a short line that stands alone first, then amid a run that later documents share
        s = said(f"short{c}", 5)
        texts |= {10 * c + 1: f"{s}\nalone {c}", **{10 * c + k: f"own {c} {k}\n{said(f'a{c}', 24)}\n\n{s}\n{said(f'b{c}', 24)}" for k in (2, 3)}}
    head = said("head", 30)  # the tail of a run whose head came first with another tail
    texts |= {200: f"{head}\nother tail", 201: f"{head}\nsame tail", 202: f"x\n{head}\nsame tail\ny"}
    rng = random.Random(4)
    texts |= {300 + k: "\n".join(rng.choice(["", " ", *(said(f"l{m}", 3 + m) for m in range(6))]) for _ in range(rng.randrange(40))) for k in range(60)}
    out = {r["doc_id"]: (r["text"], r["n_removed_lines"]) for r in line_dedup.deduplicate_lines(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    assert out == by_all_earlier_places(texts)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 5), min_size=1, max_size=12), st.lists(st.integers(0, 5), max_size=6), st.lists(st.integers(0, 5), max_size=6))
def test_winnowing_promise(run, before, after):
    count = lambda seq: np.array([3 + s for s in seq])
    code = lambda seq: np.array([(s * 7919 + 13) % 101 for s in seq])
    alone = line_dedup.winnow(code(run), count(run), 10)
    if count(run).sum() >= 10:
        inside = {p - len(before) for p in line_dedup.winnow(code(before + run + after), count(before + run + after), 10)}
        assert inside & set(alone.tolist())


# --- media -----------------------------------------------------------------------------------------
def test_checksum_is_the_formats_own():
    def slow(data):
        crc = 0
        for byte in data:
            crc ^= byte << 24
            for _ in range(8):
                crc = (crc << 1 ^ 0x04C11DB7 if crc & 0x80000000 else crc << 1) & 0xFFFFFFFF
        return crc

    for data in (b"", b"a", b"OggS" + bytes(40), os.urandom(500)):
        assert media.page_checksum(data) == slow(data)


@pytest.mark.parametrize("n", [1, 64, 255, 510, 2 * media.PACKET, 16 * media.PACKET, 48 * 255 * 2, 100_001])
def test_ogg_round_trip(n):
    samples = os.urandom(n)
    file = media.read_ogg(media.write_ogg(samples, 10))
    assert file.samples() == samples and file.bad_pages == 0 and all(s.ended for s in file.streams.values())
    for serial in file.streams:
        own = [x for x in file.timeline() if x[2] == serial]
        assert all(abs(a[1] - b[0]) < 1e-9 for a, b in zip(own, own[1:], strict=False))
        assert not own or (own[0][0] == 0 and abs(own[-1][1] * media.RATE - sum(len(x[3]) for x in own)) < 1e-6)


def test_damage_is_seen():
    raw = bytearray(media.write_ogg(os.urandom(40_000), 4))
    raw[9_000] ^= 1
    assert media.read_ogg(bytes(raw)).bad_pages > 0


def test_packets_go_over_pages_and_torn_ones_are_dropped():
    samples = os.urandom(60_000)
    raw = media.write_ogg(samples, 4)
    starts = [m.start() for m in re.finditer(b"OggS", raw) if raw[m.start() + 4] == 0]
    pages = [raw[a:b] for a, b in zip(starts, [*starts[1:], len(raw)], strict=True)]
    assert sum(bool(x[5] & media.CONTINUED) for x in pages) >= 2
    whole = {(s, a): d for a, _, s, d in media.read_ogg(raw).timeline()}
    for k in range(len(pages)):  # each page lost in turn: what is left is packets of the whole file at their own times
        file = media.read_ogg(b"".join(pages[:k] + pages[k + 1 :]))
        found = {(s, a): d for a, _, s, d in file.timeline()}
        assert all(whole.get(key) == d for key, d in found.items()) and len(found) < len(whole) + (k < 2)


def test_media_query(spark, sf, texts):
    import hashlib

    for r in media.op3_media(spark, sf).collect():
        payload = texts[r["doc_id"]].encode()
        payload += bytes(-len(payload) % 64 or (0 if payload else 64))
        assert r["verified"] and (r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))


# --- sharding, quality ---------------------------------------------------------------------------
def equal(df, found):
    names = [d[0] for d in found.description]
    assert sorted(df.select(*names).collect(), key=repr) == sorted((tuple(r) for r in found.fetchall()), key=repr)


def test_sharding_equals_sql(spark, sf, duck, texts):
    df = sharding.op4_sharding(spark, sf)
    equal(df, duck.execute(sharding.OP4_SQL))
    assert all(r["text_crc32"] == zlib.crc32(texts[r["doc_id"]].encode()) for r in df.collect())


def test_quality_equals_sql(spark, sf, duck):
    equal(quality.op7_quality(spark, sf), duck.execute(quality.OP7_SQL))


def test_host_rates_are_shrunk(spark):
    rows = [(f"h{i}", i < 1) for i in range(9) for _ in range(50)] + [("tiny", True)]
    df = spark.createDataFrame(rows, "source string, base_failed boolean").withColumns({"n_symbols": F.lit(0), "word_chars": F.lit(100), "n_dup_lines": F.lit(0), "n_lines": F.lit(1)})
    out = {r["host_key"]: r for r in quality.host_verdicts(df).collect()}
    assert not out["h0"]["host_kept"] and out["h1"]["host_kept"] and 0 < out["h1"]["host_rate"] < 0.1 and out["tiny"]["host_rate"] < 1


def test_bad_hosts_fall_and_small_or_ordinary_ones_stay(spark):
    rng = random.Random(3)
    hosts = {f"good{i}": (rng.randrange(20, 400), 0.1) for i in range(40)} | {"bad_large": (5000, 0.8), "bad_small": (60, 0.9), "few": (3, 1.0), "worse": (300, 0.25)}
    rows = [(h, k < round(n * share)) for h, (n, share) in hosts.items() for k in range(n)]
    lines = spark.createDataFrame(rows, "source string, base_failed boolean").withColumns({"n_symbols": F.lit(0), "word_chars": F.lit(100), "n_dup_lines": F.lit(0), "n_lines": F.lit(1)})
    few_bad = {r["host_key"]: r for r in quality.host_verdicts(lines.filter("source <> 'bad_large'")).collect()}
    assert [h for h, r in few_bad.items() if not r["host_kept"]] == ["bad_small"]
    assert few_bad["few"]["host_rate"] < 0.7 and 0.1 < few_bad["worse"]["host_rate"] < 0.25
    all_bad = {r["host_key"]: r for r in quality.host_verdicts(lines).collect()}  # the limit rises with the mean
    assert {h for h, r in all_bad.items() if not r["host_kept"]} == {"bad_large", "bad_small"}
    assert all_bad["bad_large"]["host_limit"] > few_bad["few"]["host_limit"]


def test_prior_takes_binomial_noise_off(spark):
    rng = np.random.default_rng(2)
    rows = [(f"h{i}", bool(x)) for i in range(300) for x in rng.random(20) < 0.2]  # all hosts alike: what differs is noise
    df = spark.createDataFrame(rows, "source string, base_failed boolean").withColumns({"n_symbols": F.lit(0), "word_chars": F.lit(100), "n_dup_lines": F.lit(0), "n_lines": F.lit(1)})
    rates = [r["host_rate"] for r in quality.host_verdicts(df).collect()]
    assert max(rates) - min(rates) < 0.1


# --- extraction ------------------------------------------------------------------------------------
@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 3), max_size=9), st.lists(st.integers(0, 3), max_size=9))
def test_shared_blocks_are_a_longest_common_subsequence(a, b):
    best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            best[i + 1][j + 1] = best[i][j] + 1 if x == y else max(best[i][j + 1], best[i + 1][j])
    found = extraction.shared_blocks(a, b)
    for positions in (found, extraction.shared_blocks(a, b, room=1)):
        rest = iter(b)
        assert len(positions) == best[-1][-1] and all(a[i] in rest for i in positions)


def test_pages(spark, sf):
    raw = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    for r in extraction.op5_extraction(spark, sf).collect():
        article = re.search(r"<article>(.*?)</article>", raw[r["page_id"]], re.S)[1]
        parts = [" ".join(html.unescape(re.sub(r"</?b>", "", x)).split()) for x in re.split(r"</?(?:p|h1)>", article.replace("<br>", " "))]
        assert r["text"] == "\n".join(x for x in parts if x)


@pytest.mark.parametrize("page, want", [
    ("<body><nav>m</nav><div>a<br>b &lt;c&gt;</div><aside>s</aside><p>d", "a b <c>\nd"),
    ("<article><header><h1>T</h1></header><p>x<div class='comments'><p>rude</div></article><footer>f</footer>", "T\nx"),
    ("<div id=cookie-notice>ok?</div><script>var a='<p>no</p>'</script><p>yes <b>bold</b></p>", "yes bold"),
    ("plain &amp; simple", "plain & simple"), ("", ""),
])
def test_blocks(page, want):
    assert "\n".join(t for t, zone, _ in extraction.blocks(page) if zone != extraction.NEVER) == want


def test_template_lines_go_without_semantic_tags(spark):
    rows = [(i, f"http://a.com/x/{i}", f"<div>Site</div><div>Own {i}</div><div>Tail</div>") for i in range(30)]
    out = extraction.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert {r["page_id"]: r["text"] for r in out} == {i: f"Own {i}" for i in range(30)}


def test_no_article_is_lost_without_its_element(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    plain = pages.withColumn("html", F.regexp_replace("html", "<(/?)article>", "<$1div>"))
    want = {r["page_id"]: r for r in extraction.extract(pages).collect()}
    assert sum(r["n_template"] for r in want.values()) > 0
    for r in extraction.extract(plain).collect():
        assert r["text"] == want[r["page_id"]]["text"], r["page_id"]


def test_repeated_pages_and_copies_keep_their_text(spark):
    said = lambda who, n: " ".join(f"{who}{k}" for k in range(n))
    menu = "<div class=top>Home</div><div class=top>News</div>"
    rows = [(i, f"http://a.org/x/{p}", f"{menu}<p>{said(t, 30)}</p><p>{said(t + 'b', 30)}</p><div>Tail</div>") for i, (p, t) in enumerate([("a", "one"), ("a", "one"), ("a?page=2", "one"), ("b", "two"), ("c", "two"), ("d", "three")])]
    rows += [(9, "http://b.org/x", rows[0][2]), (10, "http://b.org/x", rows[0][2]), (11, "http://c.org/1", f"<p>{said('one', 30)}</p><p>{said('new', 30)}</p>"), (12, "http://c.org/2", f"<p>{said('one', 30)}</p><p>{said('new', 29)} other</p>")]
    out = {r["page_id"]: r for r in extraction.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for i, t in enumerate(["one", "one", "one", "two", "two", "three"]):
        assert out[i]["text"] == f"{said(t, 30)}\n{said(t + 'b', 30)}" and out[i]["n_template"] == 3
    assert out[9]["text"] == out[10]["text"] == f"Home\nNews\n{said('one', 30)}\n{said('oneb', 30)}\nTail" and out[9]["n_template"] == 0
    assert out[11]["n_chars"] > 200


def test_differencing_equals_brute_force_over_all_pages(spark):
    rng = random.Random(6)
    rows = []
    for i in range(150):
        host, path = rng.choice(["a.com", "b.com"]), "/".join(rng.choice("xyz") for _ in range(3))
        parts = [f"<div>Site {host}</div>", *(f"<li>{rng.choice('abcdef')}</li>" for _ in range(4)), f"<p>{' '.join(rng.choice(['w', 'v', 'u']) + str(rng.randrange(40)) for _ in range(25))}</p>", "<footer>Imprint</footer>"]
        rows.append((i, f"http://{host}/{path}/{i % 7}", "".join(parts)))
    rows += [(200 + i, rows[i][1] + "/copy", rows[i][2]) for i in range(20)]
    distinct = {}
    for _, url, page in rows:
        host, path = re.match("http://([^/]+)(.*)", url).groups()
        hashes = [extraction._block_hash(t, p) for t, _, p in extraction.blocks(page)]
        prose = {extraction._block_hash(t, 0) for t, z, _ in extraction.blocks(page) if z != extraction.NEVER and t.count(" ") >= 19}
        whole = __import__("hashlib").blake2b(np.asarray(hashes, dtype=np.int64).tobytes(), digest_size=16).digest()
        never = {k for k, (_, z, _) in enumerate(extraction.blocks(page)) if z == extraction.NEVER}
        distinct[(host, whole)] = (min(path, distinct.get((host, whole), (path,))[0]), hashes, prose, never)
    order = sorted((host, path, whole, hashes, prose, never) for (host, whole), (path, hashes, prose, never) in distinct.items())
    pages = [extraction._Page(host, path, whole, hashes, prose, never, k, True) for k, (host, path, whole, hashes, prose, never) in enumerate(order)]
    gone = {}
    for p in pages:
        near = [q for q in pages if 0 < abs(q.rank - p.rank) <= extraction.NEAR and q.host == p.host and 2 * len(p.prose & q.prose) < max(1, min(len(p.prose), len(q.prose)))]
        prefix = lambda q: len(os.path.commonprefix([q.path, p.path]))  # noqa: B023, E731
        best = sorted(near, key=lambda q: (-prefix(q), abs(q.rank - p.rank), q.rank))[:1]
        shared = extraction.shared_blocks(p.blocks, best[0].blocks) if best else []
        gone[(p.host, p.whole)] = [k for k in shared if k in p.never or 2 * sum(p.blocks[k] in q.blocks for q in near) > len(near)]
    assert any(gone.values())
    out = {r["page_id"]: r["text"] for r in extraction.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for i, url, page in rows:
        found = extraction.blocks(page)
        whole = __import__("hashlib").blake2b(np.asarray([extraction._block_hash(t, p) for t, _, p in found], dtype=np.int64).tobytes(), digest_size=16).digest()
        drop = set(gone[(url.split("/")[2], whole)])
        assert out[i] == "\n".join(t for k, (t, z, _) in enumerate(found) if z != extraction.NEVER and k not in drop)


@pytest.mark.parametrize("page", ['<a "' * 200_000, "<a " * 300_000, "<div>" * 8_000 + "</span>" * 8_000, "<div>x" * 400_000, ('<a x=">" ') * 100_000, "<p><table><td>" + "<div>" * 200_000])
def test_odd_pages_take_one_pass(page):
    import time

    began = time.process_time()
    extraction.blocks(page)
    assert time.process_time() - began < 20


# --- models -----------------------------------------------------------------------------------------
def test_language_on_held_out(spark):
    df = language.op6_language(spark, "/root/testdata/sf0.01")
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang")
    rows = df.filter("held_out").join(docs, "doc_id").collect()
    assert sum(r["lang"] == r["lang_pred"] for r in rows) >= 0.98 * len(rows)


def test_binding_and_bundling_are_what_they_say():
    model = language.Profiles(["abcabd"], ["x"])
    letters = np.random.default_rng(11).choice(np.array([-1, 1], dtype=np.int8), (language.ALPHABET, language.DIMENSIONS))
    number = {c: int(model.table[ord(c)]) for c in "abcd "}
    want = np.zeros(language.DIMENSIONS)
    for gram in (" ab", "abc", "bca", "cab", "abd", "bd "):
        a, b, c = (letters[number[x]].astype(int) for x in gram)
        want += np.roll(a, 2) * np.roll(b, 1) * c
    got, _ = model.bundle(np.array([ord(c) for c in "abcabd"], dtype=np.uint32))
    assert np.array_equal(got, want)


def test_gradients_of_the_network():
    inputs = toxicity.Inputs(*buffer("a bad word here vequtin now ok", "nice day " * 20, "x"))
    net = toxicity.Network()
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    pick = np.arange(len(inputs.begin))
    label = np.resize([1.0, 0.0], len(pick))

    def loss():
        logit = net.logits(inputs, pick).astype(float)
        return np.mean(np.log1p(np.exp(-logit)) * label + np.log1p(np.exp(logit)) * (1 - label))

    dense, _ = net.gradients(inputs, pick, label)
    for name, g in dense.items():
        flat, i = net.p[name].reshape(-1), int(np.abs(g).argmax())
        keep = flat[i]
        flat[i] = keep + 0.02
        up = loss()
        flat[i] = keep - 0.02
        slope = (up - loss()) / 0.04
        flat[i] = keep
        assert abs(slope - g.reshape(-1)[i]) < 0.02 * abs(slope) + 1e-5, name


def test_windows_overlap_and_cover():
    inputs = toxicity.Inputs(*buffer(" ".join(f"w{i}" for i in range(101)), "", "one"))
    for t, n in enumerate((101, 0, 1)):
        a, b = inputs.window_start[t], inputs.window_start[t + 1]
        at = [set(range(s - inputs.first[t], s - inputs.first[t] + k)) for s, k in zip(inputs.begin[a:b], inputs.length[a:b], strict=True)]
        assert set().union(*at) == set(range(n)) and all(x & y for x, y in zip(at, at[1:], strict=False))


def test_toxicity_learns_planted_words():
    rng = random.Random(2)
    words = [f"w{i}" for i in range(300)]
    make = lambda bad: " ".join(rng.choice(words) for _ in range(rng.randint(20, 90))) + (f" zlurg{rng.randrange(99)} " if bad else " ") + " ".join(rng.choice(words) for _ in range(30))
    labels = [i % 2 for i in range(300)]
    net = toxicity.train([make(b) for b in labels], labels, steps=160)
    test = [(make(b), b) for b in [0, 1] * 60]
    inputs = toxicity.Inputs(*buffer(*(t for t, _ in test)))
    logit = net.logits(inputs)
    best = [logit[a:b].max() + net.shift for a, b in zip(inputs.window_start[:-1], inputs.window_start[1:], strict=True)]
    assert np.mean([(b > 0.847) == y for b, (_, y) in zip(best, test, strict=True)]) > 0.95


def test_mixing_reaches_its_targets(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = mixing.learn(docs, labels)
    members = mixing.materialize(mixing.memberships(docs, model), "m")
    _, goal, reached = mixing.solve(members, model.domains)
    assert np.abs(goal - reached).max() < 0.01 * goal.sum()
    out, _, shares = mixing.mixed(spark, docs, labels)
    rows = out.collect()
    assert all(abs(goal - got) < 2 * mixing.TOLERANCE for goal, got in shares.values())
    total = np.sum([np.array(r["p"]) * r["rate"] * r["n_tokens"] for r in rows], axis=0)
    assert np.abs(total - reached).max() < 0.01 * goal.sum() and all(abs(r["copies"] - r["rate"]) < 1 for r in rows)


@pytest.mark.parametrize("targets", [{"q0t1": 0.5}, {"q1t0": 0.2, "q0t0": 0.5}, {"q1t0": 0.05}])
def test_mixing_meets_far_targets(spark, sf, targets):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    model = mixing.learn(docs, labels)
    members = mixing.materialize(mixing.memberships(docs, model), "m")
    steps, goal, reached = mixing.solve(members, model.domains, targets)
    rows = members.collect()
    p, t = np.array([r["p"] for r in rows]), np.array([r["n_tokens"] for r in rows], dtype=float)
    rate = np.ones(len(p))
    for v in steps:  # the definition, row by row
        rate = np.array([max(0.0, r - mixing.STEP * (sum(a * b for a, b in zip(x, v, strict=True)) + mixing.REGULAR * (r - 1))) for r, x in zip(rate, p, strict=True)])
    assert np.allclose((p * (rate * t)[:, None]).sum(axis=0), reached) and (rate >= 0).all()
    assert np.abs(reached - goal).max() < 0.01 * goal.sum()
    assert np.abs(goal / goal.sum() - [targets.get(d, g / goal.sum()) for d, g in zip(model.domains, goal, strict=True)]).max() < 1e-9


def test_posteriors_are_the_softmax_of_word_weights():
    rng = np.random.default_rng(4)
    model = mixing.Classifier(["a", "b"], rng.standard_normal((mixing.BUCKETS, 2)).astype(np.float32), np.array([0.2, -0.1]))
    rows = ["One two one", "", "three"]
    words = kernels.Words(*buffer(*rows), folded=True)
    got = model.posteriors(words)
    for k, row in enumerate(rows):
        own = words.hash[words.first[k] : words.first[k + 1]]
        z = model.bias + sum((model.weights[mixing.Classifier.rows(np.array([h]))[0]].astype(float) for h in own), np.zeros(2)) / max(1, len(row.split())) ** 0.5
        assert np.allclose(got[k], np.exp(z) / np.exp(z).sum(), atol=1e-6)


def test_predictions_equal_a_plain_reading(spark):
    texts = {1: "Der Hund läuft schnell", 2: "le chien court vite", 3: "η γάτα τρέχει", 4: "кот бежит", 5: "猫が走る \U00020bb7", 6: "12 34"}
    model = language.Profiles([texts[1], texts[2], texts[3], texts[4]], ["de", "fr", "el", "ru"])

    def vector(text):
        clean = " " + "".join(c.lower() if c.isalpha() else " " for c in text) + " "
        clean = re.sub(" +", " ", clean)
        total = np.zeros(language.DIMENSIONS)
        for i in range(len(clean) - 2):
            bound = np.ones(language.DIMENSIONS)
            for k, c in enumerate(clean[i : i + 3]):
                bound *= np.roll(model._vector(int(model.table[ord(c)])), 2 - k)
            total += bound
        return total

    prototypes = {lang: vector(texts[i]) for lang, i in (("de", 1), ("fr", 2), ("el", 3), ("ru", 4))}
    out = {r["doc_id"]: r for r in language.identify(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), model).collect()}
    for i, text in texts.items():
        if i == 6:
            assert out[i]["lang_pred"] == "und"
            continue
        v = vector(text)
        cosine = {lang: float(v @ q / np.linalg.norm(v) / np.linalg.norm(q)) for lang, q in prototypes.items()}
        assert abs(out[i]["score"] - max(0.0, max(cosine.values()))) < 1e-4
        assert cosine[out[i]["lang_pred"]] > max(cosine.values()) - 1e-4
    assert [out[i]["lang_pred"] for i in (1, 2, 3, 4)] == ["de", "fr", "el", "ru"]


def test_rare_letters_are_not_one():
    model = language.Profiles(["abc " * 50], ["x"])
    numbers = {int(model.table[ord(c)]) for c in "ñßжλ漢字\U00030000"}
    assert len(numbers) == 7 and all(n > language.ALPHABET for n in numbers)


def test_scores_equal_a_plain_forward_pass(spark):
    rng = np.random.default_rng(9)
    net = toxicity.Network(4)
    net.shift = 0.3
    texts = {1: " ".join(f"w{k} Word{k % 7}" for k in range(30)), 2: "short one", 3: "", 4: None}
    sigmoid = lambda x: 1 / (1 + np.exp(-x))

    def plain(text):
        words = WORD.findall((text or "").translate(FOLD))
        if not words:
            return 0.0
        inputs = toxicity.Inputs(*buffer(" ".join(words)))
        h, logits = toxicity.HIDDEN, []
        starts = range(0, max(1, len(words) - (toxicity.WINDOW - toxicity.STRIDE)), toxicity.STRIDE)
        for s in starts:
            ids = inputs.word_id[s : s + toxicity.WINDOW]
            x = []
            for w in ids:
                grams = inputs.grams[inputs.gram_start[w] : inputs.gram_start[w + 1]]
                char = net.p["char"][grams].mean(axis=0) if len(grams) else np.zeros(toxicity.CHAR_DIM)
                x.append(np.concatenate([net.p["word"][inputs.word_row[w]], char]) @ net.p["input"] + net.p["bias"])
            both = []
            for side, u in enumerate((net.p["fore"], net.p["back"])):
                state, out = np.zeros(h), {}
                for t in range(len(x)) if side == 0 else range(len(x) - 1, -1, -1):
                    a, g = x[t][side * 3 * h : (side + 1) * 3 * h], state @ u
                    z, r = sigmoid(a[:h] + g[:h]), sigmoid(a[h : 2 * h] + g[h : 2 * h])
                    new = np.tanh(a[2 * h :] + r * g[2 * h :])
                    state = z * state + (1 - z) * new
                    out[t] = state
                both.append([out[t] for t in range(len(x))])
            states = np.concatenate(both, axis=1)
            weight = np.exp(states @ net.p["query"])
            logits.append((weight / weight.sum()) @ states @ net.p["out"] + net.p["out_bias"][0])
        return sigmoid(max(logits) + net.shift)

    out = {r["doc_id"]: r["score"] for r in toxicity.score(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), net).collect()}
    for i, text in texts.items():
        assert abs(out[i] - plain(text)) < 1e-4


# --- packing ------------------------------------------------------------------------------------------
def test_pieces_are_the_tokenizers(spark, sf, texts):
    from tokenizers import Tokenizer

    reference = Tokenizer.from_file(packing.default_vocabulary())
    rows = collections.defaultdict(list)
    places = collections.defaultdict(list)
    for r in packing.op10_pack(spark, sf).collect():
        rows[r["doc_id"]].append(r)
        places[r["sequence_id"]].append((r["offset"], r["length"]))
    for i, text in texts.items():
        ids = [*reference.encode(text, add_special_tokens=False).ids, 2]
        own = sorted(rows[i], key=lambda r: r["piece"])
        assert [(r["start"], r["length"]) for r in own] == packing.cut(len(ids), 1024)
        assert all(r["ids_crc32"] == zlib.crc32(np.array(ids[r["start"] : r["start"] + r["length"]], dtype="<u4").tobytes()) for r in own)
    for own in places.values():
        ends = np.cumsum([0] + [n for _, n in sorted(own)])
        assert [o for o, _ in sorted(own)] == ends[:-1].tolist() and ends[-1] <= 1024


@pytest.mark.parametrize("text", [
    "", " ", "\n\n  x", "don't  stop", "<|endoftext|> a", "a <|endoftext|> b", "<|endoftext|><|endoftext|>", "漢字 Ünï \U0001f600 123 $$$", "a\x00b", "x" * 5000,
    " " * 3000 + "x", "\n" * 2500, "a" + " \n" * 1500 + "b", " " * 1500 + "\x1cq", "x" + "\u3000" * 1200 + "  y", "z" * 5000 + "\t" * 1001 + "'s", "a" + " " * 2000 + "<|endoftext|>c",
])
def test_encoder_equals_the_library(text):
    from tokenizers import Tokenizer

    reference = Tokenizer.from_file(packing.default_vocabulary())
    assert packing.encoder(packing.default_vocabulary()).ids(text) == reference.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("text", [" " * 5_000_000, "\n" * 5_000_000 + "x", "b" * 5_000_000])
def test_encoder_takes_very_long_runs(text):
    assert len(packing.encoder(packing.default_vocabulary()).ids(text)) >= len(text) // 8


@settings(max_examples=25, deadline=None)
@given(st.dictionaries(st.integers(1, 40), st.integers(1, 60), min_size=1, max_size=20))
def test_plans_hold_each_piece_once_and_are_tight(histogram):
    plan = packing.plan_patterns(histogram, 40, rounds=60)
    held = collections.Counter()
    for pattern, n in plan:
        assert sum(pattern) <= 40 and n > 0
        for length in pattern:
            held[length] += n
    assert held == histogram
    used = sum(n for _, n in plan)
    assert used <= sum(packing.best_fit(histogram, 40).values()) * 1.25 + 1


def test_patterns_place_nearly_all_pieces(monkeypatch):
    left = {}
    pack_rest = packing.best_fit
    monkeypatch.setattr(packing, "best_fit", lambda demand, capacity: left.update(demand) or pack_rest(demand, capacity))
    rng = random.Random(8)
    histogram = {x: rng.randrange(2000, 9000) for x in range(1, 128)}
    plan = packing.plan_patterns(histogram, 128)
    held = collections.Counter()
    for pattern, n in plan:
        held.update({x: k * n for x, k in collections.Counter(pattern).items()})
    assert held == histogram and all(sum(pattern) <= 128 for pattern, _ in plan)
    assert sum(left.values()) < 0.02 * sum(histogram.values())
    assert sum(n for _, n in plan) * 128 < 1.05 * sum(x * n for x, n in histogram.items())


@pytest.mark.parametrize("pieces", [10_000, 10**8])
def test_the_program_places_the_pieces_whatever_their_number(pieces):
    rng = random.Random(pieces)
    histogram = {x: 1 + int(2 * pieces / 1023 * rng.random()) for x in range(1, 1024)}
    plan, left, bound = packing.program(histogram)
    assert sum(left.values()) < 0.1 * sum(histogram.values())
    assert sum(plan.values()) + sum(packing.best_fit(dict(left), 1024).values()) < 1.01 * bound


@settings(max_examples=30, deadline=None)
@given(st.dictionaries(st.integers(1, 12), st.integers(1, 6), min_size=1, max_size=6))
def test_dual_values_bound_every_pattern(histogram):
    demand = np.array([histogram.get(x, 0) for x in range(13)], dtype=float)
    value, bound = packing.dual_values(demand)
    best, _ = packing.knapsack(np.concatenate([[-np.inf], value[1:]]))
    assert best[12] <= 1 + 1e-9 and bound <= sum(packing.best_fit(histogram, 12).values()) + 1e-9


def test_best_fit_by_counts_is_best_fit_by_pieces():
    rng = random.Random(9)
    for _ in range(200):
        demand = {rng.randrange(1, 31): rng.randrange(1, 40) for _ in range(rng.randrange(1, 12))}
        rooms = []
        for length in sorted(demand, reverse=True):
            for _ in range(demand[length]):
                fits = [r for r in rooms if r >= length]
                if fits:
                    rooms.remove(min(fits))
                rooms.append(min(fits, default=30) - length)
        found = packing.best_fit(demand, 30)
        assert collections.Counter(rooms) == sum((collections.Counter({30 - sum(p): n}) for p, n in found.items()), collections.Counter())
        assert sum((collections.Counter({x: k * n for x, k in collections.Counter(p).items()}) for p, n in found.items()), collections.Counter()) == demand
    assert sum(packing.best_fit({7: 10**9}, 30).values()) == 250_000_000  # not a step for each piece


def test_knapsack_prices():
    lengths, prices = np.array([3, 5, 7]), np.array([2.0, 3.5, 5.1])
    best = max((2 * a + 3.5 * b + 5.1 * c, (a, b, c)) for a in range(6) for b in range(4) for c in range(3) if 3 * a + 5 * b + 7 * c <= 17)
    found = packing.best_pattern(lengths, prices, 17)
    assert abs(sum(prices[list(lengths).index(x)] * n for x, n in found.items()) - best[0]) < 1e-9
