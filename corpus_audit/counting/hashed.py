"""Counts compressed into a fixed number of hash cells.

A cell's count is the sum over all keys that fall into it, so without saturation it is an upper
bound of each of them; what collisions hide are rare keys. The number of set cells is a lower
bound of the number of distinct keys.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

U32_MAX = 2**32 - 1
#: Occupancy above which the set-cell count says little about the number of distinct keys.
FULL = 0.9


@dataclass(frozen=True)
class HashSpec:
    """m cells, a seed, a hash function (xxhash64 or md5_prefix) and a counter width (u64 or u32)."""

    m: int
    seed: int = 0
    fn: str = "xxhash64"
    counter: str = "u64"

    @classmethod
    def for_budget(cls, n_bytes: int, counter: str = "u64", **more) -> HashSpec:
        """As many cells as the byte budget holds: 8 or 4 bytes each, or one bit for ``counter="bool"``."""
        return cls(max(1, n_bytes * 8 if counter == "bool" else n_bytes // (8 if counter == "u64" else 4)), counter=counter, **more)

    def cell(self, key: Column | str) -> Column:
        key = F.col(key) if isinstance(key, str) else key
        if self.fn == "xxhash64":
            return F.pmod(F.xxhash64(F.lit(self.seed), key), F.lit(self.m))
        digits = 8 if self.m <= 2**32 else 15
        seeded = key if not self.seed else F.concat(F.lit(str(self.seed)), key)
        return F.pmod(F.conv(F.substring(F.md5(seeded.cast("binary")), 1, digits), 16, 10).cast("long"), F.lit(self.m))


def cell_counts(df: DataFrame, key: str | Column, spec: HashSpec, by: list[str] | None = None) -> DataFrame:
    """``by`` columns, cell, cnt, saturated; ``key`` is a column's name or the cell itself. At most min(m, keys) rows leave each task."""
    counted = df.groupBy(*(by or []), (spec.cell(key) if isinstance(key, str) else key).alias("cell")).agg(F.count("*").alias("cnt"))
    if spec.counter == "u32":
        return counted.select(*(by or []), "cell", F.least("cnt", F.lit(U32_MAX)).alias("cnt"), (F.col("cnt") >= U32_MAX).alias("saturated"))
    return counted.withColumn("saturated", F.lit(False))


def hot_cells(cells: DataFrame, k: int) -> DataFrame:
    """The cells whose count reaches the k-th largest (ties included); the bound is one number."""
    bound = cells.orderBy(F.desc("cnt")).limit(k).agg(F.min("cnt").alias("bound"))
    return cells.join(F.broadcast(bound), F.col("cnt") >= F.col("bound")).drop("bound")


def cold_cells(cells: DataFrame, k: int) -> DataFrame:
    """The cells whose count is at most the k-th smallest; k cells hold k keys at least."""
    bound = cells.orderBy(F.asc("cnt")).limit(k).agg(F.max("cnt").alias("bound"))
    return cells.join(F.broadcast(bound), F.col("cnt") <= F.col("bound")).drop("bound")


def occupancy(df: DataFrame, key: str, spec: HashSpec, by: list[str] | None = None) -> DataFrame:
    """``by``, set_cells, table_cells, occupancy, linear_est, nearly_full, from bitmaps of 4 KiB.

    ``linear_est`` corrects the set cells for collisions (-m ln(1 - share set)); it is null for a full table.
    """
    by = by or []
    at = spec.cell(key) + 1  # bitmap buckets count from 1
    bits = df.groupBy(*by, F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits"))
    out = bits.groupBy(*by).agg(F.sum(F.bitmap_count("bits")).alias("set_cells")).withColumn("table_cells", F.lit(spec.m).cast("long"))
    share = F.col("set_cells") / F.col("table_cells")
    linear = F.when(share < 1, F.round(-F.lit(float(spec.m)) * F.log(F.when(share < 1, 1 - share)), 0).cast("long"))
    return out.select(*by, "set_cells", "table_cells", F.round(share, 6).alias("occupancy"), linear.alias("linear_est"), (share > FULL).alias("nearly_full"))
