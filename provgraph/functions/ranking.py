"""Positions over all rows without sending all rows to one task."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def position_within(df: DataFrame, key: Column, order: list[Column], bucket: Column, out: str = "position") -> DataFrame:
    """Adds ``out``: the gapless 0-based position of each row among the rows of its ``key``, by ``bucket`` and then ``order``.

    A key may hold any share of the rows: its rows are counted per bucket (map-side combined) and numbered
    inside the bucket.  The table of bucket offsets has a row a key and bucket.
    """
    keyed = df.withColumns({"_key": key, "_sub": bucket})
    cells = keyed.groupBy("_key", "_sub").agg(F.count(F.lit(1)).alias("_n"))
    before = F.sum("_n").over(Window.partitionBy("_key").orderBy("_sub")) - F.col("_n")
    cells = cells.select(F.col("_key").alias("_k2"), F.col("_sub").alias("_s2"), before.alias("_before"))
    numbered = keyed.withColumn("_rn", F.row_number().over(Window.partitionBy("_key", "_sub").orderBy(*order)))
    joined = numbered.join(cells, F.col("_key").eqNullSafe(F.col("_k2")) & (F.col("_sub") == F.col("_s2")))
    return joined.withColumn(out, (F.col("_before") + F.col("_rn") - 1).cast("long")).drop("_key", "_sub", "_k2", "_s2", "_before", "_rn")


def salted_join(rows: DataFrame, small: DataFrame, key: str, small_key: str, spread: Column, lots: int = 16) -> DataFrame:
    """An inner equi-join in which a hot key of ``rows`` is dealt over ``lots`` tasks; ``small`` has a row a key, repeated for each."""
    salt = F.pmod(spread, F.lit(lots)).cast("int")
    left = rows.withColumn("_lot", salt)
    right = small.withColumn("_lot2", F.explode(F.sequence(F.lit(0), F.lit(lots - 1))))
    return left.join(right, (F.col(key) == F.col(small_key)) & (F.col("_lot") == F.col("_lot2"))).drop("_lot", "_lot2")


def hash_sample(df: DataFrame, key: list[Column], n: int, total: int) -> DataFrame:
    """The first ``n`` of ``total`` rows by a hash of ``key`` (ties by the key itself).

    A threshold on the hash leaves some 2 n rows before anything is sorted: a top n alone would bring n rows
    of every partition to one place.
    """
    part = F.pmod(F.xxhash64(*key), F.lit(1 << 32))
    if total > 2 * n + 1000:
        df = df.where(part < int((2 * n + 1000) / total * (1 << 32)))
    return df.orderBy(part, *key).limit(n)


def first_rows(df: DataFrame, order: list[Column], n: int, spread: list[Column], lots: int = 64) -> DataFrame:
    """The first ``n`` rows by ``order``: the first of each of ``lots`` hash lots, and then of these, so that no place gets n rows of every partition."""
    inside = Window.partitionBy("_lot").orderBy(*order)
    some = df.withColumn("_lot", F.pmod(F.xxhash64(*spread), F.lit(lots))).withColumn("_at", F.row_number().over(inside)).where(F.col("_at") <= n)
    return some.drop("_lot", "_at").orderBy(*order).limit(n)
