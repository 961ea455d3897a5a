"""Crowd-layer fusion: overlap edges with confidence, correspondence classes, propagation."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provgraph.functions.durable import cut, cut_table
from provgraph.functions.geometry import polygon_area, polygon_overlap_area
from provgraph.functions.ranking import salted_join
from provgraph.operators.components import connected
from provgraph.operators.spatial import as_boxes, overlap_join

TAU = (3, 10)


def candidates(entities: DataFrame, crowd: DataFrame, *, strategy: str = "grid", cell: int = 800, geometry: str = "box") -> DataFrame:
    """(city, entity_id, feature_id, area_a, area_b, shared): only keys and boxes go through the join.

    ``polygon``: pairs of touching boxes then fetch their ``rings``, and areas are those of the footprints;
    pairs that share none are no candidates.
    """
    if geometry not in ("box", "polygon"):
        raise ValueError(geometry)
    a = entities.select("city", "entity_id", "x0", "y0", "x1", "y1", "area")
    b = crowd.select("city", "feature_id", "x0", "y0", "x1", "y1", "area")
    pairs = overlap_join(a, b, strategy=strategy, cell=cell).select(F.col("city_a").alias("city"), "entity_id", "feature_id", "area_a", "area_b", "shared")
    if geometry == "box":
        return pairs
    side = lambda df, key, x: df.select(F.col(key).alias(f"_{x}"), F.col("rings").alias(f"rings_{x}"))
    both = pairs.select("city", "entity_id", "feature_id").join(side(entities, "entity_id", "a"), F.col("entity_id") == F.col("_a")).join(side(crowd, "feature_id", "b"), F.col("feature_id") == F.col("_b"))
    both = both.withColumn("shared", F.round(polygon_overlap_area("rings_a", "rings_b"), 6))
    return both.select("city", "entity_id", "feature_id", polygon_area(F.col("rings_a")).alias("area_a"), polygon_area(F.col("rings_b")).alias("area_b"), "shared").where("shared > 0")


def overlap() -> Column:
    return F.col("shared") / F.least("area_a", "area_b")


def jaccard() -> Column:
    return F.col("shared") / (F.col("area_a") + F.col("area_b") - F.col("shared"))


def accepted(tau: tuple[int, int] = TAU) -> Column:
    """The threshold as a whole-number test, exact at equality."""
    return tau[1] * F.col("shared") >= tau[0] * F.least("area_a", "area_b")


def edges(cands: DataFrame, *, tau: tuple[int, int] = TAU, confidence: str = "jaccard", keep_rejected: bool = False) -> DataFrame:
    """Accepted candidates with overlap, jaccard and confidence; no final matching is forced."""
    out = cands if keep_rejected else cands.where(accepted(tau))
    out = out.withColumns({"overlap": overlap(), "jaccard": jaccard()})
    if keep_rejected:
        out = out.withColumn("accepted", accepted(tau))
    return out.withColumn("confidence", F.col(confidence))


def components_of(edge: DataFrame, algo: str = "star") -> DataFrame:
    """(node, component): entities as 2 * id, features as 2 * id + 1."""
    return connected(edge.select((F.col("entity_id") * 2).alias("src"), (F.col("feature_id") * 2 + 1).alias("dst")), algo=algo)


def _kind(entities: Column, features: Column) -> Column:
    many = lambda c: c > 1
    return F.when(many(entities) & many(features), "n:m").when(many(features), "1:n").when(many(entities), "n:1").otherwise("1:1")


def classify(comp: DataFrame) -> DataFrame:
    """(component, entities, features, kind) per component."""
    side = lambda v: F.sum((F.col("node") % 2 == v).cast("long"))
    return comp.groupBy("component").agg(side(0).alias("entities"), side(1).alias("features")).withColumn("kind", _kind(F.col("entities"), F.col("features")))


def edge_classes(edge: DataFrame) -> DataFrame:
    """Edges with their component and its kind."""
    comp = cut(components_of(edge))
    known = comp.join(classify(comp).withColumnRenamed("component", "_c"), F.col("component") == F.col("_c")).select("node", "component", "kind")
    return edge.join(known, F.col("entity_id") * 2 == F.col("node")).drop("node")


def edge_kinds(edge: DataFrame) -> DataFrame:
    """Edges with their component's kind, without its number and without iteration.

    A component has one entity only if all features of that entity have no other one, and one feature likewise,
    so two steps from each end tell its kind.  Edges with a null end are left out, as in ``edge_classes``.
    """
    edge = edge.where("entity_id is not null and feature_id is not null")

    def several(own: str, other: str) -> DataFrame:
        """(_own, _several): whether any node next to this one has further neighbours."""
        more = edge.groupBy(F.col(other).alias("_o")).agg((F.min(own) != F.max(own)).alias("_m"))
        return edge.select(own, other).join(more, F.col(other) == F.col("_o")).groupBy(F.col(own).alias(f"_{own}")).agg(F.max("_m").alias(f"_several_{own}"))

    out = edge.join(several("entity_id", "feature_id"), F.col("entity_id") == F.col("_entity_id")).join(several("feature_id", "entity_id"), F.col("feature_id") == F.col("_feature_id"))
    n = lambda c: F.when(F.col(f"_several_{c}"), 2).otherwise(1)
    return out.withColumn("kind", _kind(n("entity_id"), n("feature_id"))).drop("_entity_id", "_feature_id", "_several_entity_id", "_several_feature_id")


def degree_class(edge: DataFrame) -> DataFrame:
    """Edges with the kind that their own end points' degrees show; needs no iteration."""
    n = lambda c: F.count(F.lit(1)).over(Window.partitionBy(c))
    out = edge.withColumns({"features_of_entity": n("entity_id"), "entities_of_feature": n("feature_id")})
    return out.withColumn("kind", _kind(F.col("entities_of_feature"), F.col("features_of_entity")))


def propagate(edge: DataFrame, crowd: DataFrame) -> DataFrame:
    """Per matched entity its crowd_* values, by rules of its component's kind.

    1:1 and n:1 copy the one feature's values; with several features the best edge by Jaccard decides (ties
    to the smaller feature) and tags are united; ``shared_feature`` marks components of several entities,
    ``ambiguous`` those of several on both sides, however few edges the entity itself has.
    """
    rows = edge_classes(edge).join(crowd.select("feature_id", "crowd_height", "levels", "status"), "feature_id")
    best = F.struct("jaccard", (-F.col("feature_id")).alias("t"))
    return rows.groupBy("city", "entity_id").agg(
        F.max_by("crowd_height", best).alias("crowd_height"),
        F.max_by("levels", best).alias("crowd_levels"),
        F.array_join(F.array_sort(F.collect_set("status")), ",").alias("crowd_status"),
        F.count(F.lit(1)).alias("sources"),
        F.max("jaccard").alias("best_jaccard"),
        F.first("kind").alias("kind"),
        F.first(F.col("kind").isin("n:1", "n:m")).alias("shared_feature"),
        F.first(F.col("kind") == "n:m").alias("ambiguous"),
    )


def sweep(cands: DataFrame, taus: list[tuple[int, int]]) -> DataFrame:
    """Edges, matched entities and features, and degree classes for each threshold, from one candidate join."""
    grid = F.array(*[F.struct(F.lit(p / q).alias("tau"), F.lit(p).alias("p"), F.lit(q).alias("q")) for p, q in taus])
    rows = cands.withColumn("t", F.explode(grid)).where(F.col("t.q") * F.col("shared") >= F.col("t.p") * F.least("area_a", "area_b")).select(F.col("t.tau").alias("tau"), "entity_id", "feature_id")
    n = lambda c: F.count(F.lit(1)).over(Window.partitionBy("tau", c))
    rows = rows.withColumns({"fe": n("entity_id"), "ef": n("feature_id")})
    kind = _kind(F.col("ef"), F.col("fe"))
    many = lambda k: F.sum((kind == k).cast("long"))
    return rows.groupBy("tau").agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("entity_id").alias("entities"), F.countDistinct("feature_id").alias("features"), *[many(k).alias(f"kind_{a}") for k, a in (("1:1", "11"), ("1:n", "1n"), ("n:1", "n1"), ("n:m", "nm"))])


def mutual_best(edge: DataFrame) -> DataFrame:
    """Edges that are the best of both their ends; the one-to-one alternative that fusion rejects."""
    first = lambda c, t: F.row_number().over(Window.partitionBy(c).orderBy(F.desc("jaccard"), t))
    return edge.withColumns({"_e": first("entity_id", "feature_id"), "_f": first("feature_id", "entity_id")}).where("_e = 1 and _f = 1").drop("_e", "_f")


def greedy_match(edge: DataFrame, max_rounds: int = 50) -> DataFrame:
    """Greedy one-to-one matching by Jaccard: edges that beat all their neighbours are taken, round by round."""
    left, taken = cut(edge), None
    for _ in range(max_rounds):
        best = cut(mutual_best_ordered(left))
        if best.isEmpty():
            break
        taken = best if taken is None else taken.union(best)
        left = cut(left.join(best.select(F.col("entity_id").alias("_e")), F.col("entity_id") == F.col("_e"), "left_anti").join(best.select(F.col("feature_id").alias("_f")), F.col("feature_id") == F.col("_f"), "left_anti"))
    return taken if taken is not None else edge.limit(0)


def mutual_best_ordered(edge: DataFrame) -> DataFrame:
    """Edges that are first at both ends under one total order, so that a round always takes some."""
    first = lambda c: F.row_number().over(Window.partitionBy(c).orderBy(F.desc("jaccard"), "entity_id", "feature_id"))
    return edge.withColumns({"_e": first("entity_id"), "_f": first("feature_id")}).where("_e = 1 and _f = 1").drop("_e", "_f")


def enrichment(entities: DataFrame, edge: DataFrame) -> DataFrame:
    """Share of entities with at least one edge, per city and (city null) weighted over all."""
    hit = edge.select(F.col("entity_id").alias("_e")).distinct()
    rows = entities.select("city", "entity_id").join(hit, F.col("entity_id") == F.col("_e"), "left")
    out = rows.groupingSets([["city"], []], "city").agg(F.count("_e").alias("matched"), F.count(F.lit(1)).alias("total"))
    return out.withColumn("share", F.round(F.col("matched") / F.col("total"), 6))


def poi_inside(entities: DataFrame, poi: DataFrame) -> DataFrame:
    """(poi_id, entity_id): points inside a half-open box; registered, never merged."""
    points = as_boxes(poi).withColumns({"x1": F.col("x0") + 1, "y1": F.col("y0") + 1})
    return overlap_join(points.select("city", "poi_id", "x0", "y0", "x1", "y1"), entities.select("city", "entity_id", "x0", "y0", "x1", "y1")).select(F.col("city_a").alias("city"), "poi_id", "entity_id")


def shingle_sets(docs: DataFrame, id_col: str, text: str, n: int) -> DataFrame:
    """(id, g): the distinct word n-grams of each text that has any, as an array."""
    words = F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"\s+"), lambda w: w != "")
    split = docs.select(F.col(id_col).alias("id"), words.alias("w")).where(F.size("w") >= n)
    # Shifted copies side by side: a lambda that looked back at the words would split the text for every n-gram.
    shifted = F.arrays_zip(*[F.slice("w", F.lit(k + 1), F.size("w") - (n - 1)).alias(f"a{k}") for k in range(n)])
    grams = F.array_distinct(F.transform(shifted, lambda z: F.concat_ws(" ", *[z[f"a{k}"] for k in range(n)])))
    return split.select("id", grams.alias("g"))


def shingles(docs: DataFrame, id_col: str, text: str, n: int) -> DataFrame:
    """(id, item, size): distinct word n-grams, a row each, with the set's size."""
    return shingle_sets(docs, id_col, text, n).select("id", F.size("g").cast("long").alias("size"), F.explode("g").alias("item"))


#: Items of the smaller side that are broadcast: some 20 MB.
BROADCAST_ITEMS = 200_000


def set_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """The set twin of the box measures, from two ``shingles`` tables: overlap and jaccard of all pairs that share an item.

    ``a`` is the smaller side: counted to be small it is broadcast, and items of ``b`` that it lacks are
    never shuffled; beyond that a common item's rows of ``b`` are dealt over several tasks.
    """
    a, b = a.select(F.col("id").alias("id_a"), F.col("size").alias("area_a"), F.col("item").alias("item_a")), b.select(F.col("id").alias("id_b"), F.col("size").alias("area_b"), "item")
    small = a.count() <= BROADCAST_ITEMS
    pairs = b.join(F.broadcast(a), F.col("item") == F.col("item_a")) if small else salted_join(b, a, "item", "item_a", F.xxhash64("id_b"))
    rows = pairs.groupBy("id_a", "id_b", "area_a", "area_b").agg(F.count(F.lit(1)).alias("shared"))
    return rows.withColumns({"overlap": overlap(), "jaccard": jaccard()})


def near_sets(docs: DataFrame, id_col: str, text: str, *, n: int = 5, percent: int = 80, bands: int = 16, rows: int = 2) -> DataFrame:
    """Pairs of different shingle sets with jaccard of at least ``percent``: (id_a, id_b, shared, jaccard), ids of the sets' first documents.

    Equal sets meet first, so copies make no pairs.  Candidates share a band of minimum hashes (at 0.8
    a pair is missed with probability 1e-7); they are verified on their full sets, of 64-bit hashes.
    """
    items = shingles(docs, id_col, text, n)
    least = [F.min(F.xxhash64("item", F.lit(k))).alias(f"m{k}") for k in range(bands * rows)]
    mark = items.groupBy("id", "size").agg(F.sum(F.xxhash64("item").cast("decimal(38,0)")).alias("mark"), F.bit_xor(F.xxhash64("item", F.lit(-1))).alias("mix"), *least)
    reps = cut(mark.groupBy("size", "mark", "mix").agg(F.min("id").alias("id"), *[F.first(f"m{k}").alias(f"m{k}") for k in range(bands * rows)]))
    keys = F.array(*[F.xxhash64(F.lit(b), *[F.col(f"m{b * rows + r}") for r in range(rows)]) for b in range(bands)])
    keyed = reps.select("id", "size", F.explode(keys).alias("key"))
    a, b = keyed.select(F.col("id").alias("id_a"), F.col("size").alias("area_a"), "key"), keyed.select(F.col("id").alias("id_b"), F.col("size").alias("area_b"), "key")
    fits = (F.col("id_a") < F.col("id_b")) & (100 * F.least("area_a", "area_b") >= percent * F.greatest("area_a", "area_b"))
    cands = cut(a.join(b, "key").where(fits).select("id_a", "id_b", "area_a", "area_b").distinct())
    # A pair takes its two sets along as arrays of 64-bit hashes, not as a row a shingle.
    asked = cands.select(F.explode(F.array("id_a", "id_b")).alias("_id")).distinct()
    sets = cut_table(shingle_sets(docs, id_col, text, n).join(asked, F.col("id") == F.col("_id"), "left_semi").select("id", F.transform("g", lambda x: F.xxhash64(x)).alias("set")))
    left = cands.join(sets.select(F.col("id").alias("id_a"), F.col("set").alias("set_a")), "id_a")
    both = left.join(sets.select(F.col("id").alias("id_b"), F.col("set").alias("set_b")), "id_b")
    both = both.select("id_a", "id_b", "area_a", "area_b", F.size(F.array_intersect("set_a", "set_b")).cast("long").alias("shared"))
    return both.where(100 * F.col("shared") >= percent * (F.col("area_a") + F.col("area_b") - F.col("shared"))).select("id_a", "id_b", "shared", jaccard().alias("jaccard"))
