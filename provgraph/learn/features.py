"""Ego tables: an entity's features, label and neighbourhood in one row, for both protocols."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provgraph.functions.durable import cut
from provgraph.operators import fusion
from provgraph.sources.overlay import Layers

FUNCTIONS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
#: Features that restate a target; a target never is an input, its twin is left out on demand.
TWINS = {"height": ["storeys"]}


def spatial_fold(k: int = 5) -> Column:
    """Whole tiles to folds by arithmetic on the tile."""
    return ((F.col("tx") * 7 + F.col("ty") * 13 + F.col("city") * 3) % k).cast("int")


def city_fold() -> Column:
    return (F.col("city") * 10 + spatial_fold()).cast("int")


def target(name: str) -> Column:
    """The label as a double, null where the entity has none."""
    if name == "height":
        return F.col("auth_height").cast("double")
    if name == "roof":
        return F.col("roof").cast("double")
    if name == "function":
        return (F.array_position(F.array(*[F.lit(f) for f in FUNCTIONS]), F.col("function")) - 1).cast("double")
    raise ValueError(name)


def base_features(leave_out: list[str]) -> dict[str, Column]:
    every = {
        "area": F.col("area") / 200_000.0,
        "aspect": (F.col("x1") - F.col("x0")) / (F.col("y1") - F.col("y0")),
        "tx": F.col("tx") / 8.0,
        "ty": F.col("ty") / 8.0,
        "city": F.col("city") / 5.0,
        "storeys": F.col("storeys") / 10.0,
    }
    return {k: v for k, v in every.items() if k not in leave_out}


def agnostic(entities: DataFrame, edge: DataFrame, crowd: DataFrame) -> DataFrame:
    """Evidence merged into the entity: mean crowd levels and height, without source or confidence."""
    merged = edge.select("entity_id", "feature_id").join(crowd.select("feature_id", "levels", "crowd_height"), "feature_id").groupBy(F.col("entity_id").alias("_e")).agg(F.avg("levels").alias("levels"), F.avg("crowd_height").alias("height"))
    return entities.select("entity_id", "area", "storeys").join(merged, F.col("entity_id") == F.col("_e"), "left").drop("_e")


def aware(entities: DataFrame, edge: DataFrame, predicted: DataFrame, crowd: DataFrame) -> DataFrame:
    """Coverage and agreement features: which sources there are, how many links, the best confidence, whether linked features agree in levels."""
    linked = edge.select("entity_id", "feature_id", "jaccard").join(crowd.select("feature_id", "levels"), "feature_id", "left")
    links = linked.groupBy(F.col("entity_id").alias("_e")).agg(F.count(F.lit(1)).alias("n"), F.max("jaccard").alias("best"), (F.min("levels") == F.max("levels")).alias("agree"))
    pred = predicted.select(F.col("entity_id").alias("_p")).distinct()
    rows = entities.select("entity_id").join(links, F.col("entity_id") == F.col("_e"), "left").join(pred, F.col("entity_id") == F.col("_p"), "left")
    return rows.select("entity_id", F.col("n").isNotNull().alias("has_crowd"), F.coalesce("n", F.lit(0)).alias("crowd_links"), F.coalesce("best", F.lit(0.0)).alias("best_jaccard"), F.coalesce("agree", F.lit(False)).alias("levels_agree"), F.col("_p").isNotNull().alias("has_pred"))


def normalise(edge: DataFrame, unit: bool = False) -> DataFrame:
    """Edges with share: the confidence over its sum per entity (1 / degree for unit weights); a zero sum gives no share."""
    w = F.lit(1.0) if unit else F.col("jaccard")
    total = F.sum(w).over(Window.partitionBy("entity_id"))
    return edge.withColumn("share", F.when(total > 0, w / total))


def message_pass(edge: DataFrame, crowd: DataFrame, unit: bool = False) -> DataFrame:
    """(entity_id, levels): the neighbour term of the first layer on one feature; linear, so it is aggregated before any matrix."""
    rows = normalise(edge.select("entity_id", "feature_id", "jaccard"), unit).join(crowd.select("feature_id", "levels"), "feature_id")
    return rows.groupBy("entity_id").agg(F.sum(F.col("share") * F.col("levels")).alias("levels"))


def cut_edges(edge: DataFrame, folds: DataFrame) -> DataFrame:
    """Edges whose feature touches only one fold: what training neighbourhoods may use without leaking across a border."""
    own = edge.select("entity_id", "feature_id").join(folds, "entity_id")
    one = own.groupBy(F.col("feature_id").alias("_f")).agg(F.countDistinct("fold").alias("n")).where("n = 1")
    return edge.join(one, F.col("feature_id") == F.col("_f"), "left_semi")


def ego_table(w: Layers, label: str, *, leave_out: list[str] | None = None, fold: Column | None = None, edge: DataFrame | None = None, y: Column | None = None) -> DataFrame:
    """entity_id, city, fold, y, x_agnostic, x_aware, neighbours (kind, weight, v, back), tile and mine, one row an entity.

    Neighbours of kind 1 are all other entities of the ``tile``, of weight 1, with their ``mine`` as v and x_agnostic as back.

    Edges of a feature that touches several folds are left out: nothing is read across a fold's border.
    """
    leave_out = leave_out or []
    edge = fusion.edges(fusion.candidates(w.entity, w.crowd)) if edge is None else edge
    edge = cut(cut_edges(edge, w.entity.select("entity_id", (spatial_fold() if fold is None else fold).alias("fold"))).select("entity_id", "feature_id", "jaccard"))
    e = w.entity.withColumns({"fold": spatial_fold() if fold is None else fold, "y": target(label) if y is None else y})
    base = base_features(leave_out)
    x = F.array(*[c.cast("double") for c in base.values()])
    seen = F.lit(0.0) if "storeys" in leave_out else F.col("storeys") / 10.0
    mine = F.array(seen, F.lit(0.0), F.lit(0.0), F.col("area") / 200_000.0)
    own = e.select("entity_id", "city", "fold", "tx", "ty", "y", x.alias("x_agnostic"), F.xxhash64("city", "tx", "ty").alias("tile"), mine.alias("mine"))
    # A feature's own neighbourhood: the mean of its entities' features, aggregated once for all epochs.
    means = F.array(*[F.avg(F.col("x_agnostic")[i]) for i in range(len(base))])
    back = edge.select("entity_id", F.col("feature_id").alias("_f")).join(own.select("entity_id", "x_agnostic"), "entity_id").groupBy("_f").agg(means.alias("back"))
    v = F.array(F.col("levels") / 10.0, F.coalesce(F.col("crowd_height") / 3000.0, F.lit(0.0)), F.col("crowd_height").isNotNull().cast("double"), F.col("area") / 200_000.0)
    crowd = w.crowd.select("feature_id", v.alias("v"))
    one = edge.select("entity_id", "feature_id", "jaccard").join(crowd, "feature_id").join(back, F.col("feature_id") == F.col("_f"))
    one = one.select("entity_id", F.struct(F.lit(0).alias("kind"), F.col("jaccard").alias("weight"), "v", "back").alias("nb"))
    tile = own.select(F.col("entity_id").alias("_n"), F.col("city").alias("_c"), F.col("tx").alias("_x"), F.col("ty").alias("_y"), F.col("mine").alias("v"), F.col("x_agnostic").alias("back"))
    near = own.select("entity_id", "city", "tx", "ty").join(tile, (F.col("city") == F.col("_c")) & (F.col("tx") == F.col("_x")) & (F.col("ty") == F.col("_y")) & (F.col("entity_id") != F.col("_n")))
    # All of them: a tile has a fixed size, so their number is bounded by how dense objects can stand.
    two = near.select("entity_id", F.struct(F.lit(1).alias("kind"), F.lit(1.0).alias("weight"), "v", "back").alias("nb"))
    nbs = one.union(two).groupBy(F.col("entity_id").alias("_e")).agg(F.array_sort(F.collect_list("nb")).alias("neighbours"))
    cover = aware(w.entity, edge, w.predicted, w.crowd).select(F.col("entity_id").alias("_a"), F.array(F.col("has_crowd").cast("double"), F.col("crowd_links") / 5.0, "best_jaccard", F.col("levels_agree").cast("double"), F.col("has_pred").cast("double")).alias("cover"))
    rows = own.join(nbs, F.col("entity_id") == F.col("_e"), "left").join(cover, F.col("entity_id") == F.col("_a"))
    empty = F.array().cast("array<struct<kind:int,weight:double,v:array<double>,back:array<double>>>")
    return rows.select("entity_id", "city", "fold", "y", "x_agnostic", F.concat("x_agnostic", "cover").alias("x_aware"), F.coalesce("neighbours", empty).alias("neighbours"), "tile", "mine")
