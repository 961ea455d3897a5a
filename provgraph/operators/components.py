"""Connected components by alternating star contractions, as DataFrame joins."""
from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.functions.durable import cut
from provgraph.functions.ranking import salted_join


def _minimum_of_closed_neighbourhood(pairs: DataFrame) -> DataFrame:
    """(u, v) pairs -> (u, v, m) with m the least of u and its neighbours; the minimum is map-side combined, a hub's pairs are dealt over several tasks."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("_u"), F.least("u", "m").alias("m"))
    return salted_join(pairs, least, "u", "_u", F.xxhash64("v"), lots=8).drop("_u")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _minimum_of_closed_neighbourhood(both).where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    starred = _minimum_of_closed_neighbourhood(down)
    return starred.select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u <> v").distinct()


def _mark(edges: DataFrame) -> tuple[int, int]:
    r = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
    return r[0], int(r[1] or 0)


def _by_star(edges: DataFrame, max_rounds: int) -> DataFrame:
    current = cut(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    mark = _mark(current)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        current = cut(_small_star(_large_star(current)))
        mark, last = _mark(current), mark
        if mark == last:
            break
    else:
        raise RuntimeError(f"no fixpoint after {max_rounds} rounds")
    return current.select(F.col("u").alias("node"), F.col("v").alias("component"))


def _by_label(edges: DataFrame, max_rounds: int) -> DataFrame:
    both = cut(edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct())
    label = both.select(F.col("u").alias("node"), F.col("u").alias("component")).distinct()
    for _ in range(max_rounds):
        seen = both.join(label, F.col("v") == F.col("node")).groupBy("u").agg(F.min("component").alias("near"))
        step = cut(label.join(seen, F.col("node") == F.col("u")).select("node", F.least("component", "near").alias("component"), (F.col("near") < F.col("component")).alias("moved")))
        label = step.select("node", "component")
        if step.where("moved").isEmpty():
            return label
    raise RuntimeError(f"no fixpoint after {max_rounds} rounds")


def connected(edges: DataFrame, *, src: str = "src", dst: str = "dst", algo: str = "star", max_rounds: int = 40) -> DataFrame:
    """(node, component) for every node of ``edges``; the component is its least node.

    ``star`` needs O(log^2 n) rounds and tolerates hubs (only map-side combined minima and joins);
    ``label`` needs as many rounds as the diameter.  Null endpoints are ignored; a self loop makes a
    node of its own.  No nodes: an empty table.
    """
    clean = edges.select(F.col(src).alias("u"), F.col(dst).alias("v")).where("u is not null and v is not null")
    nodes = clean.select(F.explode(F.array("u", "v")).alias("node")).distinct()
    found = {"star": _by_star, "label": _by_label}[algo](clean, max_rounds)
    found = found.withColumnRenamed("node", "_node")
    return nodes.join(found, F.col("node") == F.col("_node"), "left").select("node", F.coalesce("component", "node").alias("component"))
