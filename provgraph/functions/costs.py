"""What a query costs: seconds, rows, shuffled bytes and exchanges, from the engine's own counters."""
from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession


def shuffled_mb(spark: SparkSession) -> float:
    """MB written to shuffles by all executors since the application began."""
    store, total = spark.sparkContext._jsc.sc().statusStore(), 0
    executors = store.executorList(False)
    for i in range(executors.size()):
        total += executors.apply(i).totalShuffleWrite()
    return total / 1e6


def exchanges(df: DataFrame) -> int:
    """Exchanges in the plan as first made."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return sum("Exchange" in line and "Reused" not in line for line in plan.splitlines())


def measure(spark: SparkSession, make) -> dict:
    """Runs the query that ``make()`` gives and writes nothing: seconds (building it included), exchanges of its last plan, MB shuffled."""
    before, began = shuffled_mb(spark), time.time()
    df = make()
    planned = exchanges(df)
    df.write.format("noop").mode("overwrite").save()
    took = time.time() - began
    return {"seconds": round(took, 3), "exchanges": planned, "shuffle_mb": round(shuffled_mb(spark) - before, 1)}
