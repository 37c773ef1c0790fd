"""Shared plumbing: scratch tables in the cluster's shared folder and column helpers."""

from __future__ import annotations

import pickle
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a table of ids may be broadcast; it is counted before the hint is given.
BROADCAST_ROWS = 1_000_000


#: The folder used where the session names none; it is made once per process.
_own_root: list[str] = []


def scratch_root(spark: SparkSession) -> str:
    """The shared folder of ``spark.checkpoint.dir``; a fresh local one only where that is unset and all tasks run in this process, as in tests."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        if not _own_root:
            _own_root.append(f"file://{tempfile.mkdtemp(prefix='corpus_audit_')}")
        root = _own_root[0]
    return root.rstrip("/")


#: Scratch tables not discarded yet, oldest first.
_live: list[DataFrame] = []


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet below the shared folder and return it reread (cuts lineage)."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/scratch/{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    _live.append(out)
    return out


def made_by(work: Callable[[], DataFrame]) -> tuple[DataFrame, list[DataFrame]]:
    """The result of ``work`` and the scratch tables that it made and left."""
    start = list(_live)
    out = work()
    return out, [t for t in _live if not any(t is s for s in start)]


def discard(*tables: DataFrame) -> None:
    """Delete scratch tables that no later plan reads."""
    for table in tables:
        path = getattr(table, "_scratch_path", None)
        if path:
            spark = table.sparkSession
            target = spark._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
            _live[:] = [t for t in _live if t is not table]


def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return docs.select(*columns) if columns else docs


def whole_text(name: str = "text") -> Column:
    """The text column with null read as empty."""
    return F.coalesce(F.col(name), F.lit(""))


def held_out(doc_id: str = "doc_id") -> Column:
    """True for the fold that learning never sees: crc32 of the id as text, modulo 3, is 1."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def small_side(df: DataFrame) -> DataFrame:
    """Hint a broadcast if a count proves the (narrow) table small; else leave the choice to Spark."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def fit_in_task(sample: DataFrame, text: str, label: str, order: list[str], fit: Callable[[list[str], list], object]) -> object:
    """Run ``fit(texts, labels)`` over a bounded sample in one task and return the model.

    The sample's bound is the caller's documented parameter; rows come in a fixed order, so equal
    samples give equal models, and a lost task is simply run again.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts, labels = [], []
        for batch in batches:
            texts += batch.column(text).to_pylist()
            labels += batch.column(label).to_pylist()
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(fit(texts, labels))], type=pa.binary())], names=["model"])

    one = sample.select(text, label, *[c for c in order if c not in (text, label)]).repartition(1).sortWithinPartitions(*order)
    found = one.mapInArrow(run, "model binary").first()
    return pickle.loads(found["model"]) if found else fit([], [])  # an empty sample may run no task


def learning_sample(rows: DataFrame, key: str, label: str, limit: int) -> DataFrame:
    """``key, label`` of about ``limit`` rows of each label: those whose id's hash, as a share of its range, lies below limit / rows of the label.

    One count per label is all that is gathered; the sample depends on the ids alone and is the
    whole label where that has no more than ``limit`` rows. Null ids and labels are left out.
    """
    known = rows.select(key, label).filter(F.col(key).isNotNull() & F.col(label).isNotNull()).distinct()
    counts = known.groupBy(label).agg(F.count("*").alias("__rows"))  # one row per label
    share = F.pmod(F.xxhash64(key, F.lit(97)), F.lit(1 << 30)) / (1 << 30)
    return known.join(F.broadcast(counts), label).filter(share * F.col("__rows") < limit).select(key, label)
