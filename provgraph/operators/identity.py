"""Identity resolution of non-unique ids by content and geometry hashes; the input is never rewritten."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def content_hash(df: DataFrame, cols: list[str], out: str = "content_hash") -> DataFrame:
    """A 256-bit hash over the sorted columns; null and '' differ."""
    return df.withColumn(out, F.sha2(F.to_json(F.struct(*[F.col(c) for c in sorted(cols)]), {"ignoreNullFields": "false"}), 256))


def geometry_hash(df: DataFrame, rings: str, snap: float = 1, out: str = "geom_hash") -> DataFrame:
    """A hash of ``rings`` (array of rings of (x, y)) that doesn't depend on a ring's start or direction, or a repeated end point."""
    point = lambda p: F.struct(F.round(p["x"] / snap).cast("long").alias("x"), F.round(p["y"] / snap).cast("long").alias("y"))

    def turned(r: Column) -> Column:
        at = F.array_position(r, F.array_min(r)).cast("int")
        return F.concat(F.slice(r, at, F.size(r)), F.slice(r, F.lit(1), at - 1))

    def canonical(r: Column) -> Column:
        r = F.transform(r, point)
        r = F.when((F.size(r) > 1) & (F.element_at(r, 1) == F.element_at(r, -1)), F.slice(r, F.lit(1), F.size(r) - 1)).otherwise(r)
        return F.when(F.size(r) > 0, F.array_min(F.array(turned(r), turned(F.reverse(r)))))

    return df.withColumn(out, F.sha2(F.to_json(F.array_sort(F.transform(rings, canonical))), 256))


def resolve(df: DataFrame, id_cols: list[str], content_cols: list[str], *, geom_col: str | None = None, policy: str = "merge_or_rename") -> DataFrame:
    """Records with a unique ``new_id`` (the id columns joined by '-', and '#r' from the second variant on), merged_n and reason.

    ``merge_or_rename``: records of one id with equal content and geometry become one; different
    ones get ids of their own in the order of their hash.  ``merge_only``: one record an id, whatever
    its content.  ``rename_only``: every record stays.  Records with a null id keep a null id; equal ones merge.
    """
    hashed = content_hash(df, content_cols)
    if geom_col:
        hashed = hashed.withColumn("content_hash", F.sha2(F.concat_ws("|", "content_hash", geom_col), 256))
    old = F.concat_ws("-", *[F.col(c).cast("string") for c in id_cols])
    null_id = F.lit(False)
    for c in id_cols:
        null_id = null_id | F.col(c).isNull()
    hashed = hashed.withColumns({"old_id": F.when(~null_id, old), "_key": F.when(null_id, F.concat(F.lit("null-"), F.col("content_hash"))).otherwise(old)})
    rest = [c for c in df.columns]
    if policy == "rename_only":
        order = Window.partitionBy("_key").orderBy("content_hash", *rest)
        out = hashed.withColumns({"variant": F.row_number().over(order), "merged_n": F.lit(1).cast("long")})
    else:
        keys = ["_key", "old_id"] + (["content_hash"] if policy == "merge_or_rename" else [])
        kept = F.min(F.struct(*(["content_hash"] if policy == "merge_only" else []), *rest)).alias("_r")
        out = hashed.groupBy(*keys).agg(kept, F.count(F.lit(1)).alias("merged_n")).select(*keys, "merged_n", "_r.*")
        out = out.withColumn("variant", F.dense_rank().over(Window.partitionBy("_key").orderBy("content_hash")) if policy == "merge_or_rename" else F.lit(1))
    new = F.when(F.col("variant") == 1, F.col("old_id")).otherwise(F.concat_ws("#", "old_id", F.col("variant").cast("string")))
    reason = F.when(F.col("variant") > 1, "renamed").when(F.col("merged_n") > 1, "merged").otherwise("kept")
    return out.withColumns({"new_id": new, "reason": reason}).drop("_key", "variant")


def boundary_duplicates(df: DataFrame, content: str, tile: str) -> DataFrame:
    """(content_md5, copies, tiles): equal content delivered in more than one tile."""
    return df.groupBy(F.md5(content).alias("content_md5")).agg(F.count(F.lit(1)).alias("copies"), F.countDistinct(tile).alias("tiles")).where("tiles > 1")


def report(df: DataFrame, id_cols: list[str], content_cols: list[str], by: list[str] | None = None) -> DataFrame:
    """Duplicated ids, records that merging removes, records that renaming changes, and their share of the input."""
    one = content_hash(df, content_cols).groupBy(*(by or []), *id_cols, "content_hash").agg(F.count(F.lit(1)).alias("n"))
    ids = one.groupBy(*(by or []), *id_cols).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("variants"))
    out = ids.groupBy(*(by or [])).agg(
        F.sum("n").alias("records"),
        F.sum((F.col("n") > 1).cast("long")).alias("duplicate_ids"),
        F.sum(F.when(F.col("n") > 1, F.col("n")).otherwise(0)).alias("records_affected"),
        F.sum(F.col("n") - F.col("variants")).alias("merged_away"),
        F.sum(F.col("variants") - 1).alias("renamed"),
    )
    return out.withColumn("share_of_input", F.round(F.col("records_affected") / F.col("records"), 6))
