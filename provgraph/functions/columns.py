"""Operators that work on tables with any columns: none of their own names may meet one of the table's."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType


def column(name: str) -> Column:
    """The column of exactly this name, whatever characters it has."""
    return F.col("`" + name.replace("`", "``") + "`")


def free_name(columns: list[str], base: str) -> str:
    """``base``, or it with underscores before it, so that it names none of ``columns`` (whose case doesn't count)."""
    taken = {c.lower() for c in columns}
    while base.lower() in taken:
        base = "_" + base
    return base


def packed(df: DataFrame, **own: Column) -> DataFrame:
    """``df`` as one column ``row``, beside the operator's ``own``: they can't clash."""
    return df.select(F.struct(*map(column, df.columns)).alias("row"), *[v.alias(k) for k, v in own.items()])


def unpacked(df: DataFrame, columns: list[str], **added: Column) -> DataFrame:
    """The packed table's ``columns`` and what the operator adds; a column of the same name as an added one gives way to it."""
    gone = {k.lower() for k in added}
    df = df.select("row", *[v.alias(f"added{i}") for i, v in enumerate(added.values())])  # before any name of the table's comes up
    return df.select(*[F.col("row").getField(c).alias(c) for c in columns if c.lower() not in gone], *[F.col(f"added{i}").alias(k) for i, k in enumerate(added)])


def schema_with(df: DataFrame, **added: str) -> StructType:
    """The schema of ``df`` and fields of these names and types (DDL) after it."""
    return StructType([*df.schema.fields, *(StructField(name, StructType.fromDDL(f"x {kind}")[0].dataType) for name, kind in added.items())])


def mapped(df: DataFrame, run, schema: StructType) -> DataFrame:
    """``df.mapInArrow`` for columns of any names: ``run`` gets batches whose columns are in order, but named c0, c1 and so on."""
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))]).mapInArrow(run, schema)


def hashable(df: DataFrame) -> list[Column]:
    """The columns that Spark's hash functions take (no maps or variants, on any level)."""
    return [column(c) for c, kind in df.dtypes if "map<" not in kind and "variant" not in kind] or [F.lit(0)]
