"""Late rows, repeated runs and running state of the streams."""

import duckdb
from pyspark.sql import functions as F

from corpus_audit.counting.hashed import HashSpec, cell_counts
from corpus_audit.plans.registry import ORACLES, QUERIES
from corpus_audit.sources.io import documents
from corpus_audit.streaming import streams
from corpus_audit.text.ngrams import grams


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    schema = "event_id long, ts timestamp, event_type string"
    for k, rows in enumerate([[(1, "2024-01-01 00:10:00")], [(2, "2024-01-05 00:00:00")], [(7, "2024-01-05 05:00:00")], [(8, "2024-01-05 06:00:00")], [(3, "2024-01-01 00:20:00"), (4, "2024-01-05 00:30:00")], [(5, "2024-01-09 00:00:00")], [(6, "2024-01-12 00:00:00")]]):
        df = spark.createDataFrame([(i, t, "x") for i, t in rows], "event_id long, t string, event_type string").select("event_id", F.to_timestamp("t").alias("ts"), "event_type")
        df.coalesce(1).write.parquet(f"{tmp_path}/in/f{k}")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"{tmp_path}/in")
    counted = streams.drained(streams.event_counts(stream, "1 hour", late="1 day"))
    out = {r["d"]: r["n"] for r in counted.select(F.date_format("win_start", "yyyy-MM-dd HH").alias("d"), "n").collect()}
    assert out["2024-01-01 00"] == 1 and out["2024-01-05 00"] == 2, out


def test_cells_are_merged_once(spark, sf, tmp_path):
    spec = HashSpec(1024, fn="md5_prefix")
    for _ in range(2):  # the second run finds nothing new
        streams.merge_cells(streams.source(spark, sf, "documents"), f"file://{tmp_path}/s", 1, spec)
    want = cell_counts(grams(documents(spark, sf), 1), "gram", spec).select("cell", "cnt")
    assert streams.cells(spark, f"file://{tmp_path}/s").exceptAll(want).count() == 0


def test_index_and_running_distinct(spark, sf, tmp_path):
    streams.append_index(streams.source(spark, sf, "documents"), f"file://{tmp_path}/i")
    assert spark.read.parquet(f"{tmp_path}/i/index").select("doc_id").distinct().count() == 200
    docs = streams.source(spark, sf, "documents").select(F.col("source").alias("corpus"), "text")
    last = streams.drained(streams.running_distinct(docs, 1 << 15), "update").groupBy("corpus").agg(F.max("set_cells").alias("n"))
    want = grams(documents(spark, sf), 1, keep=["corpus"]).groupBy("corpus").agg(F.countDistinct(HashSpec(1 << 15).cell("gram")).alias("n"))
    assert last.exceptAll(want).count() == 0


def test_sessions_meet_over_batches_and_no_event_is_late(spark, tmp_path):
    """Files out of order in time; the third joins sessions of the first two, and ends that touch join too, as in the SQL."""
    files = [
        [(1, "2024-01-05 00:00:00.000001"), (1, "2024-01-05 00:50:00"), (None, "2024-01-05 00:00:00")],
        [(1, "2024-01-01 10:00:00"), (2, "2024-01-01 10:00:00.5"), (None, "2024-01-05 00:30:00.000001")],
        [(1, "2024-01-05 00:25:00"), (2, "2024-01-01 10:30:00.5"), (1, "2024-01-01 10:30:00.000001")],
    ]
    for k, rows in enumerate(files):
        spark.createDataFrame(rows, "user_id long, t string").select("user_id", F.to_timestamp_ntz("t").alias("ts")).coalesce(1).write.mode("append").parquet(f"{tmp_path}/events.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    want = con.sql(ORACLES["stream_sessions"]).fetchall()
    held = {t.name for t in spark.catalog.listTables()}
    got = QUERIES["stream_sessions"](spark, str(tmp_path)).select("user_id", "session_start", "session_end", "n")
    assert {t.name for t in spark.catalog.listTables()} == held, "rows are kept on the driver"
    assert sorted(map(tuple, got.collect()), key=repr) == sorted(want, key=repr) and len(want) == 6
