"""The corpus pipeline: five stages over ``documents``, each stored as Parquet and reread by the next.

quality rules -> line dedup -> MinHash near-dedup -> mixing to target weights -> best-fit packing
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from corpus_audit.llm import line_dedup, mixing, near_dup, packing, quality
from corpus_audit.llm.common import discard, made_by, materialize

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]
#: Scratch tables that the stage before made.
_before: list[DataFrame] = []


def _tidy(stage: Stage) -> Stage:
    """Delete the scratch tables of the stage before: by contract its result was written before the next one begins."""

    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        discard(*_before)
        out, _before[:] = made_by(lambda: stage(spark, docs, sf_dir))
        return out

    return run_stage


#: (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame, with the columns of docs but for the last.
STAGES = [
    ("quality rules", _tidy(quality.stage)),
    ("line dedup", _tidy(line_dedup.stage)),
    ("near dedup", _tidy(near_dup.stage)),
    ("mixing", _tidy(mixing.stage)),
    ("packing", _tidy(packing.stage)),
]

#: SQL can express neither the network of signatures nor the tokenizer; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The packed pieces of the documents that the stages keep."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        out = materialize(stage(spark, docs, sf_dir), "stage")
        discard(docs)
        docs = out
    return docs
