"""Most and least common n-grams: exact, hashed, and hashed with a certificate."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpus_audit.counting import narrow
from corpus_audit.counting.exact import bottom, tally, top
from corpus_audit.counting.hashed import HashSpec, cell_counts, hot_cells
from corpus_audit.text.ngrams import grams, window_rows

#: Cells up to which a list of cells is broadcast; they are counted before the hint is given.
BROADCAST_CELLS = 1_000_000
#: Tokens from which exact counts go by keys: shuffled strings would take ``n`` times the text.
NARROW_FROM = 10
#: Candidates that each task of the sweep keeps, as a multiple of k.
SWEEP_KEEP = 8


def top_exact(df: DataFrame, n: int, k: int) -> DataFrame:
    if n >= NARROW_FROM:
        return narrow.top(df.withColumn("corpus", F.lit("")), n, k).select("gram", "cnt").orderBy(F.desc("cnt"), "gram")
    return top(tally(grams(df, n), ["gram"]), k)


def bottom_exact(df: DataFrame, n: int, k: int) -> DataFrame:
    return bottom(tally(grams(df, n), ["gram"]), k)


def top_by_corpus(df: DataFrame, n: int, k: int) -> DataFrame:
    """corpus, gram, cnt, rnk: the k most frequent n-grams of each corpus."""
    if n >= NARROW_FROM:
        return narrow.top(df, n, k)
    counted = tally(grams(df, n, keep=["corpus"]), ["corpus", "gram"])
    return counted.withColumn("rnk", F.row_number().over(W.partitionBy("corpus").orderBy(F.desc("cnt"), "gram"))).filter(F.col("rnk") <= k)


def _cell(spec: HashSpec) -> Column:
    """The cell of a window by the fast hash of its tokens; hashing follows the explode, inside generated code."""
    return F.pmod(F.xxhash64(F.lit(spec.seed), "window"), F.lit(spec.m))


def gram_cells(df: DataFrame, n: int, spec: HashSpec, by: list[str] | None = None) -> DataFrame:
    """Cell counts of a corpus's n-grams; with the fast hash no string is built."""
    if spec.fn != "xxhash64":
        return cell_counts(grams(df, n, keep=by), "gram", spec, by)
    return cell_counts(window_rows(df, n, keep=by), _cell(spec), spec, by)


def candidates(df: DataFrame, n: int, cells: DataFrame, spec: HashSpec, few: bool) -> DataFrame:
    """gram, est_cnt, cnt of the n-grams whose cell is among ``cells`` (est_cnt is the cell's count).

    With the fast hash, strings are built only of windows whose cell is listed. ``few`` cells are broadcast; others
    meet the windows in a join on the cell.
    """
    chosen = cells.select("cell", F.col("cnt").alias("est_cnt"))
    chosen = F.broadcast(chosen) if few else chosen
    if spec.fn != "xxhash64":
        met = grams(df, n).withColumn("cell", spec.cell("gram")).join(chosen, "cell")
    else:
        met = window_rows(df, n).withColumn("cell", _cell(spec)).join(chosen, "cell")
        met = met.withColumn("gram", F.col("window") if n == 1 else F.array_join("window", " "))
    return met.groupBy("gram").agg(F.max("est_cnt").alias("est_cnt"), F.count("*").alias("cnt"))


def _settled(df: DataFrame) -> DataFrame:
    """An answer of k rows, worked out now, so that the cells it came from can be given up."""
    return df.sparkSession.createDataFrame(df.collect(), df.schema)


def _by_cells(df: DataFrame, n: int, k: int, spec: HashSpec, hot: bool) -> DataFrame:
    """The k n-grams with the largest (smallest) cell counts, ties by the n-gram.

    Many cells may tie at the bound, so they are counted before they are broadcast.
    """
    cells = gram_cells(df, n, spec).persist()
    order = F.desc("cnt") if hot else F.asc("cnt")
    bound = cells.orderBy(order).limit(k).agg((F.min if hot else F.max)("cnt")).first()[0]
    chosen = cells.filter((F.col("cnt") >= bound) if hot else (F.col("cnt") <= bound)) if bound is not None else cells
    found = candidates(df, n, chosen, spec, chosen.count() <= BROADCAST_CELLS)
    answer = _settled(found.select("gram", "est_cnt").orderBy(F.desc("est_cnt") if hot else F.asc("est_cnt"), "gram").limit(k))
    cells.unpersist()
    return answer


def top_hashed(df: DataFrame, n: int, k: int, spec: HashSpec) -> DataFrame:
    """gram, est_cnt: the k n-grams with the largest cell counts (upper bounds; false positives are possible)."""
    return _by_cells(df, n, k, spec, hot=True)


def bottom_hashed(df: DataFrame, n: int, k: int, spec: HashSpec) -> DataFrame:
    """gram, est_cnt: the k n-grams with the smallest final cell counts (rare ones that share a cell are missed)."""
    return _by_cells(df, n, k, spec, hot=False)


def top_sweep(df: DataFrame, n: int, k: int, spec: HashSpec) -> DataFrame:
    """gram, est_cnt as ``top_hashed``, in a single pass over the corpus.

    Each task counts its cells in one array of ``spec.m`` counters and keeps the SWEEP_KEEP * k n-grams whose
    cells are fullest so far; one that fills up later comes in at its next occurrence. The tasks' counters
    are added up and their candidates, k * SWEEP_KEEP each, are ranked by the sums. An n-gram that is in no task's
    list is missed, so this form, other than the two-pass one, is approximate in its choice too.
    """
    keep = SWEEP_KEEP * k

    def sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(spec.m, dtype=np.int64)
        held: dict[str, int] = {}
        for batch in batches:
            cell = batch.column("cell").to_numpy()
            counts += np.bincount(cell, minlength=spec.m)
            least = min((counts[c] for c in held.values()), default=0) if len(held) >= keep else 0
            at = np.flatnonzero(counts[cell] >= least)
            held.update(zip(batch.column("gram").take(pa.array(at)).to_pylist(), cell[at].tolist(), strict=True))
            held = dict(sorted(held.items(), key=lambda x: (-counts[x[1]], x[0]))[:keep])
        used = np.flatnonzero(counts)
        empty = pa.nulls(len(used), pa.string())
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(counts[used]), empty], names=["cell", "cnt", "gram"])
        yield pa.RecordBatch.from_arrays([pa.array(list(held.values()), type=pa.int64()), pa.array([0] * len(held), type=pa.int64()), pa.array(list(held), type=pa.string())], names=["cell", "cnt", "gram"])

    cells = grams(df, n).select("gram", spec.cell("gram").alias("cell"))
    swept = cells.mapInArrow(sweep, "cell long, cnt long, gram string")
    merged = swept.groupBy("cell").agg(F.sum("cnt").alias("est_cnt"), F.collect_set("gram").alias("grams")).filter(F.size("grams") > 0)
    return merged.select(F.explode("grams").alias("gram"), "est_cnt").orderBy(F.desc("est_cnt"), "gram").limit(k)


def top_certified(df: DataFrame, n: int, k: int, spec: HashSpec, oversample: int = 4) -> DataFrame:
    """gram, cnt, est_cnt, certified: exact counts of the grams in the ``oversample * k`` hottest cells.

    An n-gram outside those cells counts at most what the largest other cell does. If the k-th
    exact count is above that, the answer is proved; else four times as many cells are taken, until it is:
    all cells give the exact answer.
    """
    cells = gram_cells(df, n, spec).persist()
    wanted = oversample * k
    while True:
        hot = hot_cells(cells, wanted)
        bound = hot.agg(F.min("cnt")).first()[0]
        excluded = cells.filter(F.col("cnt") < (bound or 0)).agg(F.max("cnt")).first()[0] or 0
        found = _settled(candidates(df, n, hot, spec, hot.count() <= BROADCAST_CELLS).orderBy(F.desc("cnt"), "gram").limit(k))
        kth = found.agg(F.min("cnt"), F.count("*")).first()
        if excluded == 0 or (kth[1] >= k and kth[0] > excluded):
            break
        wanted *= 4
    cells.unpersist()
    return found.select("gram", "cnt", "est_cnt", F.lit(True).alias("certified"))


def distinct_exact(df: DataFrame, n: int) -> DataFrame:
    """corpus, n_distinct, share_of_tokens."""
    counted = tally(grams(df, n, keep=["corpus"]), ["corpus", "gram"])
    return counted.groupBy("corpus").agg(F.count("*").alias("n_distinct"), F.round(F.count("*") / F.sum("cnt"), 6).alias("share_of_tokens"))


def singletons(df: DataFrame, sample: int = 25, seed: str = "s") -> DataFrame:
    """A seeded random sample of the unigrams that occur once in the whole."""
    once = tally(grams(df, 1), ["gram"]).filter("cnt = 1")
    return once.select("gram", F.md5(F.concat(F.lit(seed), "gram").cast("binary")).alias("o")).orderBy("o", "gram").limit(sample).select("gram")


def context_sample(df: DataFrame, gram: str, n: int, size: int = 100, seed: str = "c", width: int = 80) -> DataFrame:
    """doc_id, excerpt: a seeded sample of documents with the n-gram, for sorting by hand."""
    hits = grams(df, n, keep=["doc_id"]).filter(F.col("gram") == gram).select("doc_id").distinct()
    chosen = hits.select("doc_id", F.md5(F.concat(F.lit(seed), F.col("doc_id").cast("string")).cast("binary")).alias("o")).orderBy("o", "doc_id").limit(size).select("doc_id")
    first = F.split(F.lit(gram), " ")[0]
    return df.join(F.broadcast(chosen), "doc_id").select("doc_id", F.substr("text", F.greatest(F.lit(1), F.instr("text", first) - width // 2), F.lit(width)).alias("excerpt"))
