"""Near duplicates by min-hash signatures and a multi-index Hamming join.

A signature comes from ``SYMBOLS`` min-hashes; two texts of similarity 0.75 differ in a quarter of
them on average. Of the first ``INDEXED`` ones 16 bits are kept, and the join promises every pair
that differs in at most ``DISTANCE`` of these symbols: by the pigeonhole principle one of the
``INDEXED / CHUNK`` chunks of such a pair holds at most one differing symbol, so each chunk is
indexed once per symbol left out. Of all min-hashes 2 bits are kept as a check: pairs met in the
index go on if at most ``CHECK_BITS`` of these bits differ, and are then confirmed on full
shingle sets. A pair at exactly 0.75 has 192 of them apart on average with a deviation of 15.5, so the check
loses a link with a chance of about 1e-5, as the distance itself does; both chances fall steeply above 0.75.

Pairs are never expanded inside a bucket as long as its members may still come together: in each
of ``ROUNDS`` rounds every bucket has one pivot, the members of other components are held against
it, each of them tries the ``TRIES`` most similar of the
``MET`` pivots that it shares most keys with, and confirmed links are contracted to components.
Only then are members of different components that share a bucket compared with each other, in blocks of
``BUCKET`` members against the bucket.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.llm import kernels as K
from corpus_audit.llm.common import discard, materialize, small_side, whole_text
from corpus_audit.llm.graph import connected_components

SYMBOLS, CHECK_BITS = 768, 260
INDEXED, CHUNK, DISTANCE = 64, 4, 31
ROUNDS, MET, TRIES = 3, 20, 4
#: Members of a bucket that one task of the last join takes on one side.
BUCKET = 512
INDEX_LANES, CHECK_LANES = INDEXED // 4, SYMBOLS // 32
LANES = [*(f"s{i}" for i in range(INDEX_LANES)), *(f"c{i}" for i in range(CHECK_LANES))]
_seeds = np.random.default_rng(977)
_MULTIPLY = (_seeds.integers(1, 2**31, SYMBOLS, dtype=np.uint32) * np.uint32(2) + np.uint32(1))[:, None]
_FLIP = _seeds.integers(0, 2**32, SYMBOLS, dtype=np.uint32)[:, None]


def min_hashes(shingles: np.ndarray) -> np.ndarray:
    """The signature of one shingle set: the lowest value under each permutation, cut to 16 mixed bits."""
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    least = np.full(SYMBOLS, 2**32 - 1, dtype=np.uint32)
    for i in range(0, len(x), 512):
        np.minimum(least, ((x[None, i : i + 512] ^ _FLIP) * _MULTIPLY).min(axis=1), out=least)
    return ((least * np.uint32(0x9E3779B1)) >> np.uint32(16)).astype(np.uint16)


_SIGNED = "doc_id long, n_shingles long, d1 long, d2 long, " + ", ".join(f"{x} long" for x in LANES)


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, off = K.text_buffer(batch.column("text"))
        n = batch.num_rows
        sizes, digests = np.zeros(n, dtype=np.int64), np.zeros((n, 2), dtype=np.int64)
        signed = np.zeros((n, SYMBOLS), dtype=np.uint16)
        for i, j in K.slices(off):
            words = K.Words(data[off[i] : off[j]], off[i : j + 1] - off[i], folded=True)
            windows = K.shingle_hashes(words.hash)
            for k in range(i, j):
                a, b = words.first[k - i], words.first[k - i + 1]
                if a < b:
                    own = K.shingle_set(words.hash[a:b], windows[a:])
                    sizes[k], digests[k], signed[k] = len(own), K.sequence_digest(words.hash[a:b]), min_hashes(own)
        index = np.ascontiguousarray(signed[:, :INDEXED]).view(np.int64)
        low = (signed & 3).astype(np.uint8)
        check = np.ascontiguousarray(low[:, ::4] | low[:, 1::4] << 2 | low[:, 2::4] << 4 | low[:, 3::4] << 6).view(np.int64)
        lanes = np.concatenate([index, check], axis=1)
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), pa.array(sizes), pa.array(digests[:, 0].copy()), pa.array(digests[:, 1].copy()), *(pa.array(lanes[:, i].copy()) for i in range(len(LANES)))],
            names=["doc_id", "n_shingles", "d1", "d2", *LANES],
        )


def signatures(docs: DataFrame) -> DataFrame:
    """One row per document: set size, a 128-bit digest of its folded words, and its signature, four symbols to a long."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text")).mapInArrow(_sign, _SIGNED)


def _index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        lanes = np.stack([batch.column(f"s{i}").to_numpy() for i in range(INDEX_LANES)], axis=1)
        chunks = np.ascontiguousarray(lanes).view(np.uint16).reshape(len(lanes), -1, CHUNK).astype(np.uint64)
        keys = []
        for left_out in range(CHUNK):
            key = np.arange(chunks.shape[1], dtype=np.uint64)[None, :] * np.uint64(CHUNK) + np.uint64(left_out)
            for s in range(CHUNK):
                if s != left_out:
                    key = (key << np.uint64(16)) | chunks[:, :, s]
            keys.append(key)
        flat = np.stack(keys, axis=2).reshape(len(lanes), -1)
        node = np.repeat(batch.column("node").to_numpy(), flat.shape[1])
        yield pa.RecordBatch.from_arrays([pa.array(flat.reshape(-1).astype(np.int64)), pa.array(node)], names=["key", "node"])


def _bits_apart(a: str, b: str) -> Column:
    """Check bits in which two signatures differ."""
    return reduce(lambda p, q: p + q, (F.bit_count(F.col(f"{a}{i}").bitwiseXOR(F.col(f"{b}{i}"))) for i in range(CHECK_LANES)))


def _checks(classes: DataFrame, node: str, prefix: str) -> DataFrame:
    return classes.select(F.col("node").alias(node), F.col("n_shingles").alias(f"{prefix}n"), *(F.col(f"c{i}").alias(f"{prefix}{i}") for i in range(CHECK_LANES)))


def _may_link(a: str, b: str) -> Column:
    """Set sizes that allow a similarity of 0.75, and few check bits apart."""
    sizes = 100 * F.least(f"{a}n", f"{b}n") >= 75 * F.greatest(f"{a}n", f"{b}n")
    return sizes & (_bits_apart(a, b) <= CHECK_BITS)


def _first_key(key: str, a: str, b: str) -> Column:
    """True if ``key`` is the first of the keys that two signatures (arrays of chunks) share.

    A chunk yields a common key if at most one of its four symbols differs; if none does, it yields
    four, of which the first counts.
    """

    def one_symbol(x: Column, y: Column) -> Column:
        d = x.bitwiseXOR(y)
        return reduce(lambda p, q: p | q, (d.bitwiseAND(F.lit(m)) == d for m in (0xFFFF, 0xFFFF0000, 0xFFFF00000000, -0x1000000000000)))

    slot = F.shiftrightunsigned(key, 48)
    chunk, left_out = F.floor(slot / CHUNK).cast("int"), slot % CHUNK
    return (F.array_position(F.zip_with(a, b, one_symbol), True) == chunk + 1) & ((left_out == 0) | (F.get(a, chunk) != F.get(b, chunk)))


def _to_set(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, off = K.text_buffer(batch.column("text"))
        sets = []
        for i, j in K.slices(off):
            words = K.Words(data[off[i] : off[j]], off[i : j + 1] - off[i], folded=True)
            sets += [K.shingle_set(words.hash[words.first[k] : words.first[k + 1]]).tobytes() for k in range(j - i)]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sets, type=pa.binary())], names=["node", "shingles"])


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        good = np.zeros(batch.num_rows, dtype=bool)
        for k, (a, b) in enumerate(zip(batch.column("su"), batch.column("sv"), strict=True)):
            a, b = (np.frombuffer(x.as_buffer(), dtype=np.uint64) for x in (a, b))
            low, high = sorted((len(a), len(b)))
            if 100 * low >= 75 * high:
                both = len(np.intersect1d(a, b, assume_unique=True))
                good[k] = 100 * both >= 75 * (len(a) + len(b) - both)
        yield pa.RecordBatch.from_arrays([batch.column("u").filter(pa.array(good)), batch.column("v").filter(pa.array(good))], names=["u", "v"])


def confirm_links(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """The pairs ``(u, v)`` of document ids whose full sets have 100 * intersection >= 75 * union."""
    ids = pairs.select(F.col("u").alias("doc_id")).union(pairs.select("v")).distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text"))
    sets = materialize(texts.join(small_side(ids), "doc_id", "left_semi").mapInArrow(_to_set, "node long, shingles binary"), "sets")
    left, right = (sets.select(F.col("node").alias(x), F.col("shingles").alias(f"s{x}")) for x in "uv")
    links = materialize(pairs.join(left, "u").join(right, "v").select("u", "v", "su", "sv").mapInArrow(_confirm, "u long, v long").distinct(), "links")
    discard(sets)
    return links


def _placed(shared: DataFrame, found: DataFrame | None) -> DataFrame:
    """``key, node, component`` of the bucket members; a node without links is its own component."""
    if found is None:
        return shared.select("key", "node", F.col("node").alias("component"))
    return shared.join(found, "node", "left").select("key", "node", F.coalesce("component", "node").alias("component"))


def _grown(docs: DataFrame, pairs: DataFrame, links: DataFrame | None, found: DataFrame | None, tried: DataFrame | None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links, components and tried pairs (both ways) after one more table of candidate pairs."""
    both = pairs.union(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
    tried = both if tried is None else tried.union(both)
    new = confirm_links(docs, pairs)
    if found is not None and not new.head(1):
        return links, found, tried
    links = materialize(new if links is None else links.union(new), "links")
    components = materialize(connected_components(links), "found")
    discard(new, *([found] if found is not None else []))
    return links, components, tried


def near_duplicates(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept`` for every row of ``docs(doc_id, text, ...)``.

    Null and wordless texts have no shingles and are linked with nothing: their component is their
    own id. A null ``doc_id`` gets a null component and is kept. Rows that repeat an id count as one
    document, so they share a component. Ties do not arise: a component is named by its smallest id.
    """
    base = materialize(signatures(docs), "signed")
    usable = base.filter((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull())
    # Copies collapse to their smallest id; equal words have equal signatures, so any of them serves.
    classes = materialize(usable.groupBy("d1", "d2").agg(F.min("doc_id").alias("node"), *(F.min(x).alias(x) for x in ["n_shingles", *LANES])), "classes")
    keys = classes.select("node", *LANES[:INDEX_LANES]).mapInArrow(_index, "key long, node long").repartition("key")
    met = keys.groupBy("key").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).filter("lo < hi").select("key")
    shared = materialize(keys.join(met, "key", "left_semi"), "shared")
    links, found, tried = None, None, None
    for turn in range(ROUNDS):
        placed = _placed(shared, found)
        # Each chunk (later each bucket) puts the nodes in an order of its own, so that a node meets several pivots.
        order = F.xxhash64("node", F.shiftrightunsigned("key", 50) if turn == 0 else F.col("key"), F.lit(turn))
        pivots = placed.groupBy("key").agg(F.min_by("node", order).alias("pivot"), F.min_by("component", order).alias("home"), F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo < hi").select("key", "pivot", "home")
        # A node meets one pivot at most for each of its keys, so the lists below are bounded; it goes on with those it shares most keys with.
        stars = placed.join(pivots, "key").filter("component != home").groupBy(F.col("node").alias("u"), F.col("pivot").alias("v")).agg(F.count("*").alias("n"))
        stars = stars.groupBy("u").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("n")).alias("n"), "v"))), 1, MET).alias("best")).select("u", F.explode("best.v").alias("v"))
        scored = stars.join(_checks(classes, "u", "p"), "u").join(_checks(classes, "v", "q"), "v").filter(_may_link("p", "q")).select("u", "v", _bits_apart("p", "q").alias("apart"))
        nearest = scored.groupBy("u").agg(F.slice(F.array_sort(F.collect_list(F.struct("apart", "v"))), 1, TRIES).alias("best"))
        near = materialize(nearest.select("u", F.explode("best.v").alias("v")), "near")
        links, found, tried = _grown(docs, near, links, found, tried)

    # What is left: bucket mates that no pivot brought into one component.
    placed = _placed(shared, found)
    split = placed.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.ceil(F.count("*") / BUCKET).alias("blocks")).filter("lo < hi").select("key", "blocks")
    chunks = classes.select("node", F.array(*LANES[:INDEX_LANES]).alias("chunks"))
    carried = materialize(placed.join(split, "key"), "mixed").join(_checks(classes, "node", "c"), "node").join(chunks, "node")
    one, two = (carried.select("key", block.alias("block"), F.col("node").alias(x), F.col("component").alias(f"of_{x}"), F.col("chunks").alias(f"{x}_chunks"), F.col("cn").alias(f"{y}n"), *(F.col(f"c{i}").alias(f"{y}{i}") for i in range(CHECK_LANES))) for x, y, block in (("u", "p", F.pmod(F.xxhash64("node"), "blocks")), ("v", "q", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))))
    rest = one.join(two, (one["key"] == two["key"]) & (one["block"] == two["block"]) & (F.col("of_u") > F.col("of_v")) & _may_link("p", "q") & _first_key(one["key"], "u_chunks", "v_chunks")).select("u", "v").distinct()
    rest = materialize(rest.join(tried, ["u", "v"], "left_anti"), "rest")
    links, found, tried = _grown(docs, rest, links, found, tried)

    # A class's component, named by its smallest member.
    placed = classes.select("d1", "d2", "node").join(found, "node", "left").select("d1", "d2", F.coalesce("component", "node").alias("component"))
    out = base.select("doc_id", "n_shingles", "d1", "d2").join(placed, ["d1", "d2"], "left").select("doc_id", "n_shingles", F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("component")).otherwise(F.col("doc_id")).alias("component_id"))
    result = materialize(out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id"))), "near_dup")
    discard(base, classes, shared, links, found)
    return result


def op9_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The class of near duplicates of every document; see ``near_duplicates`` for odd rows. Texts of any length are read whole, and columns other than doc_id and text are not read."""
    return near_duplicates(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: the one with the smallest id (one row, if it is repeated).

    Documents without a word or an id stay; an empty table stays empty; other columns are carried along untouched.
    """
    found = near_duplicates(spark, docs)
    gone = small_side(found.filter(~F.col("kept")).select("doc_id").distinct())
    repeated = materialize(found.filter(F.col("doc_id").isNotNull()).groupBy("doc_id").count().filter("count > 1").select("doc_id"), "repeated")
    left = docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
    if not repeated.head(1):
        return left
    # Rows that repeat an id and a text are reduced to one; only those are shuffled.
    again = small_side(repeated)
    return left.join(again, "doc_id", "left_anti").select(*docs.columns).union(left.join(again, "doc_id", "left_semi").select(*docs.columns).dropDuplicates(["doc_id", "text"]))
