"""Table functions for SQL users; the DataFrame path stays with built-in expressions."""

from __future__ import annotations

import re
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

_TOKEN = re.compile(r"\w+(?:[.'’]\w+)*|[^\w\s]")


@udtf(returnType="pos int, gram string")
class ExplodeNgrams:
    """``SELECT * FROM explode_ngrams(text, n)``."""

    def eval(self, text: str, n: int) -> Iterator[tuple[int, str]]:
        words = _TOKEN.findall(text or "")
        for i in range(len(words) - n + 1):
            yield i, " ".join(words[i : i + n])


def register(spark: SparkSession, sf_dir: str | None = None, tables: tuple[str, ...] = ("documents", "pages", "benchmark", "labels", "conversations", "events", "orders", "customer", "nation")) -> None:
    """Register the table function and, given a directory, a view for each table."""
    spark.udtf.register("explode_ngrams", ExplodeNgrams)
    for t in tables if sf_dir else ():
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
