"""Line dedup by winnowing over line hashes.

A document is a sequence of non-blank lines. For each line that begins a stretch of at least
``MIN_WORDS`` words, the window is the shortest such stretch, and the line with the lowest hash in
it is a fingerprint; so any run of whole lines with that many words holds a fingerprint wherever
it occurs. Windows are also taken as the shortest stretch that ends with a line. Positions are joined by
fingerprint: those of a line that is a fingerprint in no other place go, and every window of the others
is held against the first place (order: doc_id, then position) of its whole content. A match reaches
both ways as far as its overlapping windows do, since a run of enough words is the union of the windows of both
kinds that lie in it. So a line goes if and only if it lies in a run of at least ``MIN_WORDS``
words that equals one at any earlier place; the first occurrence of a line is never deleted.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpus_audit.llm import kernels as K
from corpus_audit.llm.common import BROADCAST_ROWS, discard, materialize, small_side, whole_text

#: Words from which a repeated run is deleted.
MIN_WORDS = 25
_LAST = 2**63 - 1
_Q = [int(x) * 4 + 1 for x in np.random.default_rng(5150).integers(1, 2**61, 2)]


def windows_of(hashes: np.ndarray, words: np.ndarray, first: np.ndarray, min_words: int = MIN_WORDS) -> tuple[np.ndarray, ...]:
    """Start, stop and fingerprint of the windows of some documents, whose lines are ``first[d]:first[d + 1]``.

    First come the shortest stretches from each line on, then the shortest ones up to a line that
    are not among them; those have the fingerprint of the window that begins with them. Ties go to
    the last line.
    """
    n = len(hashes)
    total = np.concatenate([[0], np.cumsum(words, dtype=np.int64)])
    begin, end = np.repeat(first[:-1], np.diff(first)), np.repeat(first[1:], np.diff(first))
    stop = np.searchsorted(total, total[:-1] + min_words)
    start = np.flatnonzero(stop <= end)
    mark, low = np.arange(n), hashes.copy()
    for step in range(1, int((stop[start] - start).max()) if len(start) else 0):
        live = start[start + step < stop[start]]
        live = live[hashes[live + step] <= low[live]]
        mark[live], low[live] = live + step, hashes[live + step]
    back = np.searchsorted(total, total[1:] - min_words, side="right") - 1
    last = np.flatnonzero(back >= begin)
    last = last[stop[back[last]] != last + 1]
    a, b = np.concatenate([start, back[last]]), np.concatenate([stop[start], last + 1])
    return a, b, mark[a]


def winnow(hashes: np.ndarray, words: np.ndarray, min_words: int = MIN_WORDS) -> np.ndarray:
    """Positions of the fingerprints of one document's lines; ties in a window go to its last line."""
    return np.unique(windows_of(hashes, words, np.array([0, len(hashes)]), min_words)[2]).astype(np.int32)


def content(hashes: np.ndarray, a: np.ndarray, b: np.ndarray, q: int) -> np.ndarray:
    """A hash of the line hashes ``a[i]:b[i]``, whatever stands before and behind."""
    n = len(hashes)
    terms = hashes.view(np.uint64) * K.powers(q, n + 1)[:n]
    total = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(terms, dtype=np.uint64)])
    back = K.powers(pow(q, -1, 2**64), n + 1)[a]
    return K.mix((total[b] - total[a]) * back + (b - a).astype(np.uint64)).view(np.int64)


def line_arrays(words: K.Words, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, ...]:
    """Of the non-blank lines of some rows: first line of each row, two hashes, word counts, and line numbers in the row.

    A line is its sequence of words, so white space at its ends or between words does not count.
    """
    n_words = len(words.hash)
    row_of = np.searchsorted(words.first, np.arange(n_words), side="right") - 1
    breaks = np.flatnonzero(data == 0x0A)
    line_of = np.searchsorted(breaks, words.start)
    new = np.ones(n_words, dtype=bool)
    new[1:] = (row_of[1:] != row_of[:-1]) | (line_of[1:] != line_of[:-1])
    begin = np.flatnonzero(new)
    counts = np.diff(np.append(begin, n_words))
    hashes = []
    place = (np.arange(n_words) - np.repeat(begin, counts)) if n_words else np.zeros(0, dtype=np.int64)
    for q in _Q:
        terms = words.hash * K.powers(q, int(place.max()) + 1 if n_words else 1)[place]
        hashes.append(K.mix(np.add.reduceat(terms, begin) + counts.astype(np.uint64)) if n_words else np.zeros(0, dtype=np.uint64))
    number = line_of[begin] - np.searchsorted(breaks, off[:-1])[row_of[begin]]
    return np.searchsorted(begin, words.first), hashes[0].view(np.int64), hashes[1].view(np.int64), counts.astype(np.int32), number.astype(np.int32)


_MARKS = "ord long, th long, k1 long, k2 long, pos int, windows binary"
_CELL = np.dtype([("w1", "<i8"), ("w2", "<i8"), ("at", "<i4"), ("n", "<i4")])


def _winnowed(batches: Iterator[pa.RecordBatch], min_words: int) -> Iterator[pa.RecordBatch]:
    """A row for each fingerprint: its hash, its place among the non-blank lines, and its windows (content hash, first line, lines)."""
    for batch in batches:
        data, off = K.text_buffer(batch.column("text"))
        ids, th = batch.column("ord").to_numpy(), batch.column("th").to_numpy()
        for i, j in K.slices(off):
            words = K.Words(data[off[i] : off[j]], off[i : j + 1] - off[i], folded=False)
            first, h1, h2, n, _ = line_arrays(words, data[off[i] : off[j]], off[i : j + 1] - off[i])
            a, b, mark = windows_of(h1, n, first, min_words)
            order = np.argsort(mark, kind="stable")
            a, b, mark = a[order], b[order], mark[order]
            row = np.searchsorted(first, mark, side="right") - 1
            cells = np.empty(len(a), dtype=_CELL)
            cells["w1"], cells["w2"], cells["at"], cells["n"] = content(h1, a, b, _Q[0]), content(h2, a, b, _Q[1]), a - first[row], b - a
            begin = np.flatnonzero(np.diff(mark, prepend=-1))
            at, row = mark[begin], row[begin]
            bounds = pa.py_buffer((np.append(begin, len(a)) * _CELL.itemsize).astype(np.int32))
            windows = pa.BinaryArray.from_buffers(pa.binary(), len(begin), [None, bounds, pa.py_buffer(cells.tobytes())])
            yield pa.RecordBatch.from_arrays([*(pa.array(c) for c in (ids[i:j][row], th[i:j][row], h1[at], h2[at], (at - first[row]).astype(np.int32))), windows], names=["ord", "th", "k1", "k2", "pos", "windows"])


def _unfolded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each window of the fingerprints."""
    for batch in batches:
        cells = [np.frombuffer(x.as_buffer(), dtype=_CELL) for x in batch.column("windows")]
        size = [len(x) for x in cells]
        flat = np.concatenate([np.zeros(0, dtype=_CELL), *cells])
        own = (np.repeat(batch.column(c).to_numpy(), size) for c in ("ord", "th"))
        yield pa.RecordBatch.from_arrays([*(pa.array(c) for c in own), *(pa.array(flat[c].copy()) for c in ("w1", "w2", "at", "n"))], names=["ord", "th", "w1", "w2", "at", "n"])


def _keyed(docs: DataFrame) -> DataFrame:
    """Row identity: the id (null last) and a hash of the text; rows equal in both are one document."""
    return docs.select("*", F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("__ord"), F.xxhash64(whole_text()).alias("__th"))


def repeated_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """``ord, th, drop``: for each document with repeated runs, the places (from 0, among the non-blank lines) of the lines to delete."""
    slim = _keyed(docs.select("doc_id", "text")).select(F.col("__ord").alias("ord"), F.col("__th").alias("th"), whole_text().alias("text"))
    found = materialize(slim.mapInArrow(lambda it: _winnowed(it, min_words), _MARKS), "winnowed")
    at = F.struct("ord", "th", "pos")
    marks = found.groupBy("k1", "k2").agg(F.min(at).alias("a"), F.max(at).alias("b")).filter("a < b").select("k1", "k2")
    marks = materialize(marks, "marks")
    kept = found.join(small_side(marks), ["k1", "k2"], "left_semi").select("ord", "th", "windows")
    held = materialize(kept.mapInArrow(_unfolded, "ord long, th long, w1 long, w2 long, at int, n int"), "held")
    own = F.struct("ord", "th", "at")
    firsts = materialize(held.groupBy("w1", "w2").agg(F.min(own).alias("src"), F.max(own).alias("top")).filter("src < top").select("w1", "w2", "src"), "firsts")
    # A content that stands in very many places is met by broadcast, or else by a join that adaptive execution splits.
    later = held.join(small_side(firsts), ["w1", "w2"]).filter(F.col("src") < own)
    lines = F.sequence("at", F.col("at") + F.col("n") - 1)
    out = materialize(later.groupBy("ord", "th").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_set(lines)))).alias("drop")), "runs")
    discard(found, marks, held, firsts)
    return out


def deduplicate_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """All columns of ``docs`` with ``text`` freed of later repeated runs, and ``n_lines`` and ``n_removed_lines`` (which replace columns so named).

    ``n_lines`` counts lines with a word; blank lines always stay. Texts without repeats, null ones
    included, are returned unchanged; a text all of whose lines are repeats becomes the empty text
    or its blank lines. Copies of a row (same id, same text) are one document and get one result.
    """
    runs = repeated_lines(docs, min_words)
    size = runs.agg(F.count("*"), F.coalesce(F.sum(F.size("drop")), F.lit(0))).first()
    if size[0] <= BROADCAST_ROWS // 4 and size[1] <= 2 * BROADCAST_ROWS:
        runs = F.broadcast(runs)
    kept = [c for c in docs.columns if c not in ("n_lines", "n_removed_lines")]
    runs = runs.select(F.col("ord").alias("__o"), F.col("th").alias("__t"), F.col("drop").alias("__drop"))
    joined = _keyed(docs.select(*kept)).join(runs, (F.col("__ord") == F.col("__o")) & (F.col("__th") == F.col("__t")), "left")
    joined = joined.select(*kept, "__drop")
    schema = T.StructType([*(f for f in joined.schema if f.name != "__drop"), T.StructField("n_lines", T.LongType()), T.StructField("n_removed_lines", T.LongType())])
    return joined.mapInArrow(_freed, schema)


def _freed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts without the lines whose numbers (among those with a word) are in ``__drop``."""
    for batch in batches:
        texts, n_lines, n_removed = [], [], []
        for text, drop in zip(batch.column("text"), batch.column("__drop"), strict=True):
            text, drop = text.as_py(), drop.as_py()
            parts = (text or "").split("\n")
            solid = [k for k, x in enumerate(parts) if x.strip(" \t\x0b\x0c\r")]
            if drop:
                gone = {solid[i] for i in drop}
                text = "\n".join(x for k, x in enumerate(parts) if k not in gone)
            texts.append(text)
            n_lines.append(len(solid))
            n_removed.append(len(drop or ()))
        names = [c for c in batch.schema.names if c != "__drop"]
        columns = [pa.array(texts, type=pa.string()) if c == "text" else batch.column(c) for c in names]
        yield pa.RecordBatch.from_arrays([*columns, pa.array(n_lines, type=pa.int64()), pa.array(n_removed, type=pa.int64())], names=[*names, "n_lines", "n_removed_lines"])


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``doc_id, n_lines, n_removed_lines, text`` of every document.

    Null and empty texts have no lines and stay as they are; texts and lines of any length are read whole; rows that
    repeat an id and a text count as one document, ties in a window go to its last line; an empty table gives an
    empty result; columns other than doc_id and text are not read.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = deduplicate_lines(docs)
    return out.select("doc_id", "n_lines", "n_removed_lines", "text")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without their repeated runs; a document all of whose lines were repeats elsewhere goes.

    Null and empty texts stay as they are; an empty table stays empty; other columns are carried along untouched.
    """
    others = [c for c in docs.columns if c != "text"]
    out = deduplicate_lines(docs.select(F.struct(*others).alias("__row"), "doc_id", "text"))
    left = out.filter(~((F.col("n_removed_lines") > 0) & (F.col("n_removed_lines") == F.col("n_lines"))))
    return left.select("__row.*", "text").select(*docs.columns)
