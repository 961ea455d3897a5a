"""All workload queries, by key, with their SQL."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provgraph.operators import fusion, provenance
from provgraph.plans import city, formats, learning, questioning, relational  # noqa: F401  they register their queries
from provgraph.plans.registry import QUERIES, SQL
from provgraph.sources.overlay import Layers
from provgraph.streaming import events  # noqa: F401


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fuses the layers and gives, per city, heights with their coverage: authoritative first, crowd where it is absent."""
    w = Layers(spark, sf_dir)
    edge = fusion.edges(fusion.candidates(w.entity, w.crowd))
    best = provenance.resolve_value(provenance.height_facts(w.entity, edge, w.crowd)).select(F.col("entity_id").alias("_e"), "value", "source")
    rows = w.entity.select("entity_id", "city").join(best, F.col("entity_id") == F.col("_e"), "left").withColumnRenamed("value", "height")
    return provenance.coverage_agg(rows, ["city"], "height")


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(SQL)
