"""Accuracy measures as aggregates over prediction tables."""
from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def per_class_f1(pred: DataFrame, by: list[str]) -> DataFrame:
    cells = pred.where("y is not null and yhat is not null").groupBy(*by, "y", "yhat").agg(F.count(F.lit(1)).alias("n"))
    both = cells.select(*by, F.explode(F.array(F.struct(F.col("y").alias("c"), F.when(F.col("y") == F.col("yhat"), F.col("n")).otherwise(0).alias("tp"), F.when(F.col("y") != F.col("yhat"), F.col("n")).otherwise(0).alias("fn"), F.lit(0).cast("long").alias("fp")), F.struct(F.col("yhat").alias("c"), F.lit(0).cast("long").alias("tp"), F.lit(0).cast("long").alias("fn"), F.when(F.col("y") != F.col("yhat"), F.col("n")).otherwise(0).alias("fp")))).alias("k")).select(*by, "k.*")
    out = both.groupBy(*by, "c").agg(F.sum("tp").alias("tp"), F.sum("fn").alias("fn"), F.sum("fp").alias("fp")).where("tp + fn > 0")
    return out.withColumn("f1", 2 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn")))


def macro_f1(pred: DataFrame, by: list[str]) -> DataFrame:
    """Mean F1 over the classes that occur in the truth."""
    return per_class_f1(pred, by).groupBy(*by).agg(F.avg("f1").alias("value")).withColumn("metric", F.lit("macro_f1"))


def r2(pred: DataFrame, by: list[str]) -> DataFrame:
    """1 - SSE / SST of the pooled rows; null for a constant target."""
    rows = pred.where("y is not null and yhat is not null")
    d = F.col("y") - F.col("yhat")
    out = rows.groupBy(*by).agg(F.sum(d * d).alias("sse"), (F.var_pop("y") * F.count("y")).alias("sst"))
    return out.select(*by, F.when(F.col("sst") > 1e-12, 1 - F.col("sse") / F.col("sst")).alias("value"), F.lit("r2").alias("metric"))


def auc(pairs: DataFrame, by: list[str], ranges: int = 64) -> DataFrame:
    """Area under the ROC curve of (label 0/1, score) with ties counted half, from counts per distinct score.

    Scores are dealt over ``ranges`` of near equal share; the running count is taken inside a range and the
    ranges' totals, a bounded table, are added: no task sees all scores of a group.
    """
    n = pairs.groupBy(*by, "score").agg(F.sum("label").alias("pos"), F.sum(1 - F.col("label")).alias("neg"))
    key = F.struct(*by)
    edges = n.groupBy(key.alias("_k")).agg(F.percentile_approx("score", [i / ranges for i in range(1, ranges)]).alias("_edges"))
    placed = n.join(F.broadcast(edges), key == F.col("_k")).withColumn("_range", F.size(F.filter("_edges", lambda e: e < F.col("score")))).drop("_edges")
    totals = placed.groupBy(F.col("_k").alias("_k2"), F.col("_range").alias("_r2")).agg(F.sum("neg").alias("_n"))
    before = F.sum("_n").over(Window.partitionBy("_k2").orderBy("_r2")) - F.col("_n")
    inside = F.sum("neg").over(Window.partitionBy("_k", "_range").orderBy("score").rowsBetween(Window.unboundedPreceding, -1))
    rows = placed.withColumn("_inside", F.coalesce(inside, F.lit(0))).join(F.broadcast(totals.withColumn("_before", before)), (F.col("_k") == F.col("_k2")) & (F.col("_range") == F.col("_r2")))
    rows = rows.withColumn("hits", F.col("pos") * (F.col("_before") + F.col("_inside") + F.col("neg") / 2))
    return rows.groupBy(*by).agg(F.sum("hits").alias("h"), F.sum("pos").alias("p"), F.sum("neg").alias("n")).select(*by, F.when((F.col("p") > 0) & (F.col("n") > 0), F.col("h") / (F.col("p") * F.col("n"))).alias("auc"))
