"""Incremental versions of the counting analyses on Structured Streaming."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.counting.hashed import HashSpec, cell_counts
from corpus_audit.search.index import build
from corpus_audit.text.ngrams import grams


def source(spark: SparkSession, sf_dir: str, name: str, files_per_trigger: int = 1) -> DataFrame:
    """A table's files as a stream, with the schema of the table (a glob, since the table may be one file)."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{sf_dir}/{name[:-1]}[{name[-1]}].parquet")
    # Watermarks need an instant; the tables hold local times.
    return stream.withColumns({f.name: F.col(f.name).cast("timestamp") for f in schema if f.dataType.typeName() == "timestamp_ntz"})


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and return what it put out.

    Appended rows and the stream's state go to the shared folder of ``spark.checkpoint.dir``. Only where that is unset, as in tests,
    or for the small tables of the other modes, are they kept in memory.
    """
    spark, name = stream.sparkSession, f"stream_{uuid.uuid4().hex}"
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True)
    if root and mode == "append":
        path = f"{root.rstrip('/')}/streams/{name}"
        writer.format("parquet").option("checkpointLocation", f"{path}/state").start(f"{path}/rows").awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{path}/rows")
    writer.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def event_counts(events: DataFrame, size: str = "1 hour", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """win_start, event_type, n in tumbling (or sliding) windows; rows later than ``late`` are dropped."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    counted = events.withWatermark("ts", late).groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("win_start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """user_id, session_start, session_end, n."""
    counted = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"))
    return counted.select("user_id", F.col("s.start").alias("session_start"), F.col("s.end").alias("session_end"), "n")


def dedup(docs: DataFrame, keep: str = "30 days") -> DataFrame:
    """digest of each text on its first arrival; the state holds 16 bytes a text and forgets those that arrived more than ``keep`` ago."""
    arrived = docs.select(F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("digest"), F.current_timestamp().alias("arrived"))
    return arrived.withWatermark("arrived", keep).dropDuplicatesWithinWatermark(["digest"]).select("digest")


def dedup_within(events: DataFrame, key: str = "event_id", late: str = "1 day") -> DataFrame:
    """As above with a state that forgets keys older than the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def merge_cells(docs: DataFrame, path: str, n: int, spec: HashSpec) -> None:
    """Add each batch's cell counts to a table partitioned by batch; a repeated batch replaces its own part."""

    def store(batch: DataFrame, batch_id: int) -> None:
        cell_counts(grams(batch, n), "gram", spec).select("cell", "cnt").write.mode("overwrite").parquet(f"{path}/cells/batch={batch_id}")

    docs.writeStream.foreachBatch(store).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()


def cells(spark: SparkSession, path: str) -> DataFrame:
    """cell, cnt over all batches so far."""
    return spark.read.parquet(f"{path}/cells").groupBy("cell").agg(F.sum("cnt").alias("cnt"))


def merge_sessions(events: DataFrame, path: str, gap: str = "30 minutes") -> None:
    """Add each batch's own sessions to a table partitioned by batch; a repeated batch replaces its own part. No event is late."""

    def store(batch: DataFrame, batch_id: int) -> None:
        sessions(batch, gap).write.mode("overwrite").parquet(f"{path}/sessions/batch={batch_id}")

    events.writeStream.foreachBatch(store).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()


def merged_sessions(spark: SparkSession, path: str) -> DataFrame:
    """As ``sessions`` over all batches so far: those of different batches that meet are one."""
    schema = "user_id long, session_start timestamp, session_end timestamp, n long"
    length = F.expr("make_interval(0, 0, 0, 0, 0, 0, CAST(unix_micros(session_end) - unix_micros(session_start) AS DECIMAL(20, 0)) / 1000000)")
    parts = spark.read.schema(schema).parquet(f"{path}/sessions")
    merged = parts.groupBy("user_id", F.session_window("session_start", length).alias("s")).agg(F.sum("n").alias("n"))
    return merged.select("user_id", F.col("s.start").alias("session_start"), F.col("s.end").alias("session_end"), "n")


def append_index(docs: DataFrame, path: str) -> None:
    """Append each batch's postings; a repeated batch replaces its own part."""

    def store(batch: DataFrame, batch_id: int) -> None:
        build(batch).write.mode("overwrite").parquet(f"{path}/index/batch={batch_id}")

    docs.writeStream.foreachBatch(store).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()


def running_distinct(docs: DataFrame, m: int = 1 << 15) -> DataFrame:
    """corpus, set_cells, table_cells after each batch: a bitmap of token cells is kept per corpus."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        bits = bytearray(state.get[0]) if state.exists else bytearray(m // 8)
        for frame in frames:
            for cell in frame["cell"]:
                bits[cell >> 3] |= 1 << (cell & 7)
        state.update((bytes(bits),))
        yield pd.DataFrame({"corpus": [key[0]], "set_cells": [sum(b.bit_count() for b in bits)], "table_cells": [m]})

    cut = grams(docs, 1, keep=["corpus"]).select("corpus", HashSpec(m).cell("gram").alias("cell"))
    return cut.groupBy("corpus").applyInPandasWithState(update, "corpus string, set_cells long, table_cells long", "bits binary", "update", "NoTimeout")
