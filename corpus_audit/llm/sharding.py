"""Contiguous shards of nearly equal bytes by global prefix sums.

Documents are put in one total order (doc_id, null first, then text checksum) by range
partitioning. Each partition sums its own sizes; the running totals over partitions (one row
each) turn local prefixes into global ones, and a document belongs to the shard in whose equal
share of the bytes its middle lies.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpus_audit.llm.common import discard, materialize, whole_text

SHARDS = 8


def _prefix(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Bytes and rows before each row within its partition."""
    part, size_before, rows_before = TaskContext.get().partitionId(), 0, 0
    for batch in batches:
        sizes = batch.column("size").to_numpy()
        ends = size_before + np.cumsum(sizes)
        n = batch.num_rows
        columns = [pa.array(ends - sizes), pa.array(np.arange(rows_before, rows_before + n)), pa.array(np.full(n, part, dtype=np.int32))]
        yield pa.RecordBatch.from_arrays([*batch.columns, *columns], names=[*batch.schema.names, "size_before", "rows_before", "part"])
        if n:
            size_before, rows_before = int(ends[-1]), rows_before + n


def shard_sizes(sized: DataFrame, n_shards: int = SHARDS) -> DataFrame:
    """``sized(doc_id, size, text_crc32)`` plus ``shard`` and ``slot``, by contiguous equal-byte cuts.

    Repeated rows are neighbours and take slots of their own; an empty table gives an empty result.
    A shard's bytes differ from the mean by less than one document at each end.
    """
    spark = sized.sparkSession
    stored = materialize(sized.select("doc_id", "size", "text_crc32").withColumn("row", F.monotonically_increasing_id()), "sizes")
    order = [F.col("doc_id").asc_nulls_first(), F.col("text_crc32"), F.col("row")]
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = stored.repartitionByRange(n, *order).sortWithinPartitions(*order)
    prefixed = materialize(dealt.mapInArrow(_prefix, "doc_id long, size long, text_crc32 long, row long, size_before long, rows_before long, part int"), "prefix")
    totals = prefixed.groupBy("part").agg(F.sum("size").alias("bytes"), F.count("*").alias("n_rows"))
    before = W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)  # one row for each partition
    every = W.orderBy("part").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    starts = totals.select("part", F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("b0"), F.coalesce(F.sum("n_rows").over(before), F.lit(0)).alias("r0"), F.sum("bytes").over(every).alias("total"))
    placed = prefixed.join(F.broadcast(starts), "part")
    middle = 2 * (F.col("b0") + F.col("size_before")) + F.col("size")
    shard = F.least(F.lit(n_shards - 1), F.expr(f"({n_shards} * (2 * (b0 + size_before) + size)) div greatest(2 * total, 1)"))
    placed = placed.select("doc_id", "size", "text_crc32", shard.cast("int").alias("shard"), (F.col("r0") + F.col("rows_before")).alias("rank"))
    firsts = placed.groupBy("shard").agg(F.min("rank").alias("first"))  # one row for each shard
    return placed.join(F.broadcast(firsts), "shard").select("doc_id", "size", "text_crc32", "shard", (F.col("rank") - F.col("first")).alias("slot"))


def sizes(docs: DataFrame) -> DataFrame:
    """Per row: UTF-8 bytes of the text plus 1 and the crc32 of the text (null: empty)."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(whole_text()) + 1).cast("long").alias("size"), F.crc32(whole_text().cast("binary")).alias("text_crc32"))


def write_shards(docs: DataFrame, path: str, n_shards: int = SHARDS) -> None:
    """Write all columns of ``docs`` as Parquet below ``path``, one directory ``__shard=k`` per shard, rows in slot order.

    Rows of a repeated (doc_id, text) go to the first of their shards.
    """
    placed = shard_sizes(sizes(docs), n_shards).groupBy("doc_id", "text_crc32").agg(F.min(F.struct("shard", "slot")).alias("__at"))
    keyed = docs.withColumn("__id", F.col("doc_id").cast("long")).withColumn("__crc", F.crc32(whole_text().cast("binary")))
    placed = placed.select(F.col("doc_id").alias("__pid"), F.col("text_crc32").alias("__pcrc"), "__at")
    joined = keyed.join(placed, keyed["__id"].eqNullSafe(placed["__pid"]) & (F.col("__crc") == F.col("__pcrc")))
    out = joined.select(*docs.columns, F.col("__at.shard").alias("__shard"), F.col("__at.slot").alias("__slot"))
    out.repartitionByRange("__shard", "__slot").sortWithinPartitions("__shard", "__slot").drop("__slot").write.partitionBy("__shard").parquet(path)


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shard and slot of every document.

    Null and empty texts count one byte; texts of any length count whole; ties in the order go by the text's hash; repeated rows get
    slots of their own; an empty table gives an empty result; columns other than doc_id and text are not read.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = shard_sizes(sizes(docs))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


_CRC_TABLE = "(SELECT list(c ORDER BY n) AS t FROM (SELECT n, list_reduce(list_concat([n], range(8)), lambda a, k: CASE WHEN a % 2 = 1 THEN xor(a >> 1, 3988292384) ELSE a >> 1 END) AS c FROM range(256) r(n)))"
#: crc32 is not a function of DuckDB, so it is folded over the bytes.
OP4_SQL = f"""
WITH b AS (SELECT doc_id, coalesce(text, '') AS text, hex(encode(coalesce(text, ''))) AS h FROM documents),
s AS (SELECT doc_id, CAST(octet_length(encode(text)) + 1 AS BIGINT) AS size,
  CASE WHEN text = '' THEN 0 ELSE xor(list_reduce(list_concat([4294967295::BIGINT], list_transform(range(octet_length(encode(text))), lambda i: CAST('0x' || substr(h, 2 * i + 1, 2) AS BIGINT))),
       lambda a, x: xor(a >> 8, t[CAST(xor(a & 255, x) AS INTEGER) + 1])), 4294967295) END AS text_crc32 FROM b, {_CRC_TABLE}),
p AS (SELECT *, sum(size) OVER (ORDER BY doc_id ROWS UNBOUNDED PRECEDING) - size AS before, sum(size) OVER () AS total, row_number() OVER (ORDER BY doc_id) AS r FROM s),
x AS (SELECT doc_id, size, text_crc32, CAST(least({SHARDS - 1}, ({SHARDS} * (2 * before + size)) // (2 * total)) AS INTEGER) AS shard, r FROM p)
SELECT doc_id, size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'bytes' AS law, shard, CAST(r - min(r) OVER (PARTITION BY shard) AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard FROM x
"""
