"""Shallow walk embeddings; they know only the nodes that they walked on, so they stay at pilot scale."""
from __future__ import annotations

from pyspark.ml.feature import Word2Vec
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provgraph.functions.durable import cut


def walk(edge: DataFrame, *, walks: int = 4, length: int = 8, p: float = 1.0, q: float = 1.0, seed: int = 1) -> DataFrame:
    """(start, k, path): second-order walks between entities and features; a step back has weight 1 / p, one onward 1 / q.

    On a bipartite graph a step never stays at distance one, so two weights are all; with p = q = 1
    these are plain entity-feature-entity metapath walks.
    """
    both = cut(edge.select((F.col("entity_id") * 2).alias("u"), (F.col("feature_id") * 2 + 1).alias("v")).select(F.explode(F.array(F.struct("u", "v"), F.struct(F.col("v").alias("u"), F.col("u").alias("v")))).alias("e")).select("e.u", "e.v").distinct())
    now = both.where("u % 2 = 0").select(F.col("u").alias("start")).distinct().withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(walks)))).withColumn("path", F.array("start"))
    for step in range(length):
        u = (F.pmod(F.xxhash64("start", "k", F.lit(step), "v", F.lit(seed)), F.lit(1 << 30)) + 1) / (1 << 30)
        back = F.coalesce(F.col("v") == F.get("path", F.size("path") - 2), F.lit(False))
        # The largest u ** (1 / weight) is a draw in proportion to the weights.
        draw = F.log(u) / F.when(back, 1 / p).otherwise(1 / q)
        nxt = now.join(both, F.element_at("path", -1) == F.col("u")).withColumn("_r", F.row_number().over(Window.partitionBy("start", "k").orderBy(draw.desc(), "v"))).where("_r = 1")
        now = cut(nxt.select("start", "k", F.concat("path", F.array("v")).alias("path")))
    return now


def embed(edge: DataFrame, *, size: int = 8, **options) -> DataFrame:
    """(_node, z) of the entities walked on; others have no row."""
    rows = walk(edge, **options).select(F.transform("path", lambda x: x.cast("string")).alias("path"))
    model = Word2Vec(vectorSize=size, minCount=0, seed=1, inputCol="path", numPartitions=1, maxIter=2).fit(rows)
    v = model.getVectors().select(F.col("word").cast("long").alias("w"), vector_to_array("vector").alias("z"))
    return v.where("w % 2 = 0").select((F.col("w") / 2).cast("long").alias("_node"), "z")
