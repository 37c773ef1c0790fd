"""Accuracy measures of the hashed methods against exact ones."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpus_audit.counting.hashed import HashSpec


def with_estimates(df: DataFrame, key: str, spec: HashSpec) -> DataFrame:
    """``key``, its exact cnt, its cell and the cell's est."""
    exact = df.groupBy(key).agg(F.count("*").alias("cnt")).withColumn("cell", spec.cell(key))
    # Cells are sums of exact counts, so the rows are not read again.
    cells = exact.groupBy("cell").agg(F.sum("cnt").alias("est"))
    return exact.join(cells, "cell")


def error_report(df: DataFrame, key: str, spec: HashSpec) -> DataFrame:
    """n_grams, n_inflated, max_inflation: a cell never counts less than the key."""
    gap = F.col("est") - F.col("cnt")
    return with_estimates(df, key, spec).agg(F.count("*").alias("n_grams"), F.count_if(gap > 0).alias("n_inflated"), F.max(gap).alias("max_inflation"))


def collision_report(df: DataFrame, key: str, spec: HashSpec) -> DataFrame:
    """table_cells, set_cells, colliding_cells, n_keys, load."""
    per_cell = df.select(key).distinct().groupBy(spec.cell(key).alias("cell")).agg(F.count("*").alias("n"))
    return per_cell.agg(F.lit(spec.m).cast("long").alias("table_cells"), F.count("*").alias("set_cells"), F.count_if(F.col("n") > 1).alias("colliding_cells"), F.sum("n").alias("n_keys"), F.round(F.sum("n") / spec.m, 6).alias("load"))


def bound_check(df: DataFrame, key: str, spec: HashSpec) -> DataFrame:
    """Keys whose cell counts less than they do (none, if counters do not saturate)."""
    return with_estimates(df, key, spec).filter(F.col("est") < F.col("cnt"))


def answer_quality(found: DataFrame, truth: DataFrame, key: str = "gram") -> DataFrame:
    """n_found, n_truth, n_both, precision, recall of one answer set against another."""
    both = found.select(key, F.lit(1).alias("f")).join(truth.select(key, F.lit(1).alias("t")), key, "full")
    out = both.agg(F.count("f").alias("n_found"), F.count("t").alias("n_truth"), F.count_if(F.col("f").isNotNull() & F.col("t").isNotNull()).alias("n_both"))
    return out.withColumns({"precision": F.round(F.try_divide("n_both", "n_found"), 6), "recall": F.round(F.try_divide("n_both", "n_truth"), 6)})


def seed_agreement(df: DataFrame, column: str, seeds: tuple[int, int] = (1, 2)) -> DataFrame:
    """Cluster sizes whose number differs between two seeded hashes of a column: size, diff (no rows if they agree)."""
    def sizes(seed: int) -> DataFrame:
        clusters = df.groupBy(F.md5(F.concat(F.lit(str(seed)), F.col(column)).cast("binary"))).agg(F.count("*").alias("size"))
        return clusters.groupBy("size").agg(F.count("*").alias(f"n{seed}"))

    a, b = (sizes(s) for s in seeds)
    diff = F.coalesce(F.col(f"n{seeds[0]}"), F.lit(0)) - F.coalesce(F.col(f"n{seeds[1]}"), F.lit(0))
    return a.join(b, "size", "full").select("size", diff.alias("diff")).filter("diff <> 0")
