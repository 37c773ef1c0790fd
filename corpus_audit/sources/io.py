"""Sources and sinks: explicit schemas, corpus mapping, common corpus formats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: What every analysis reads; corpora without a field have nulls there.
CORE_SCHEMA = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("corpus", T.StringType()), T.StructField("subset", T.StringType()),
    T.StructField("text", T.StringType()), T.StructField("url", T.StringType()), T.StructField("created", T.TimestampType()), T.StructField("lang", T.StringType()),
])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """A scan of fewer splits than cores, dealt over all of them; larger inputs are left as they are.

    For analyses that do much work per text. ``df`` must be a plain scan, whose partitions are known without running it.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df if df.isStreaming or df._jdf.rdd().getNumPartitions() >= cores else df.repartition(cores)


def load_corpus(source: DataFrame, mapping: dict[str, str | Column]) -> DataFrame:
    """Map a source's columns to the core schema; fields that the mapping leaves out are null."""
    given = {k: F.col(v) if isinstance(v, str) else v for k, v in mapping.items()}
    return source.select(*(given.get(f.name, F.lit(None)).cast(f.dataType).alias(f.name) for f in CORE_SCHEMA))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The documents table as corpora: source is the corpus, language the subset."""
    return load_corpus(table(spark, sf_dir, "documents"), {"doc_id": "doc_id", "corpus": "source", "subset": "lang", "text": "text", "lang": "lang"})


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pages table as five corpora, with the visible text of the html."""
    from corpus_audit.text.html import visible_text

    return load_corpus(table(spark, sf_dir, "pages"), {"doc_id": "page_id", "corpus": F.concat(F.lit("p"), (F.col("page_id") % 5).cast("string")), "text": visible_text(F.col("html")), "url": "url"})


def read_jsonl(spark: SparkSession, path: str, schema: T.StructType = CORE_SCHEMA) -> DataFrame:
    """JSON lines, plain or compressed; the schema is given, never inferred."""
    return spark.read.schema(schema).json(path)


def read_csv(spark: SparkSession, path: str, schema: T.StructType = CORE_SCHEMA) -> DataFrame:
    return spark.read.schema(schema).option("header", True).option("multiLine", True).option("escape", '"').csv(path)


def read_text(spark: SparkSession, path: str, corpus: str) -> DataFrame:
    """One document per file, named by its path."""
    files = spark.read.text(path, wholetext=True).select(F.col("value").alias("text"), F.input_file_name().alias("file"))
    return load_corpus(files, {"doc_id": F.xxhash64("file"), "corpus": F.lit(corpus), "text": "text", "url": "file"})


def write_corpus(df: DataFrame, path: str) -> None:
    """Parquet partitioned by corpus, so that runs over one corpus prune the rest."""
    df.write.partitionBy("corpus").mode("overwrite").parquet(path)


def write_index(postings: DataFrame, name: str, buckets: int = 64) -> None:
    """Postings as a table bucketed and sorted by term: a term's lookup reads one bucket."""
    postings.write.bucketBy(buckets, "term").sortBy("term").mode("overwrite").saveAsTable(name)


def write_json(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def drain(df: DataFrame) -> None:
    """Run a plan to its end without storing the rows, for timing."""
    df.write.format("noop").mode("overwrite").save()
