"""Trust classes, provenance-filtered facts, cross-source agreement and coverage-aware aggregates."""
from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Default order of trust; only that the authoritative source comes first is given.
TRUST = {"auth": 4, "recon": 3, "crowd": 2, "pred": 1}


def trust_of(source: Column) -> Column:
    """The trust class, computed from the source that an edge or prefix shows."""
    return reduce(lambda acc, kv: acc.when(source == kv[0], kv[1]), list(TRUST.items())[1:], F.when(source == "auth", TRUST["auth"])).cast("int")


def attach(entities: DataFrame, values: DataFrame, attr: str, prefix: str, on: str = "entity_id") -> DataFrame:
    """Adds a derived value under its source's prefix; refuses to touch a column that is there."""
    name = f"{prefix}_{attr}"
    if prefix == "auth" or name in entities.columns:
        raise ValueError(f"{name} would overwrite an existing or authoritative value")
    return entities.join(values.select(F.col(on).alias("_on"), F.col(attr).alias(name)), F.col(on) == F.col("_on"), "left").drop("_on")


def height_facts(entities: DataFrame, edge: DataFrame, crowd: DataFrame, *, sources: list[str] | None = None, min_trust: int | None = None, min_conf: float | None = None) -> DataFrame:
    """(entity_id, city, source, trust, confidence, value) of the attribute height.

    Source and trust filters pick the layers before anything is scanned: a layer that can't answer
    is not part of the plan.
    """
    wanted = [s for s in (sources or ["auth", "crowd"]) if min_trust is None or TRUST[s] >= min_trust]
    parts = []
    if "auth" in wanted:
        parts.append(entities.where("auth_height is not null").select("entity_id", "city", F.lit("auth").alias("source"), F.lit(1.0).alias("confidence"), F.col("auth_height").cast("double").alias("value")))
    if "crowd" in wanted:
        known = edge if min_conf is None else edge.where(F.col("jaccard") >= min_conf)
        parts.append(known.join(crowd.where("crowd_height is not null").select("feature_id", "crowd_height"), "feature_id").select("entity_id", "city", F.lit("crowd").alias("source"), F.col("jaccard").alias("confidence"), F.col("crowd_height").cast("double").alias("value")))
    if not parts:
        return entities.limit(0).select("entity_id", "city", F.lit("").alias("source"), F.lit(0.0).alias("confidence"), F.lit(0.0).alias("value"), F.lit(0).alias("trust"))
    out = reduce(DataFrame.unionByName, parts).withColumn("trust", trust_of(F.col("source")))
    return out if min_conf is None else out.where(F.col("confidence") >= min_conf)


def layer_facts(entities: DataFrame, predicted: DataFrame, recon: DataFrame, *, min_trust: int | None = None, min_conf: float | None = None) -> DataFrame:
    """(entity_id, city, attr, source, trust, confidence, value) of what the predicted and reconstructed layers say.

    A predicted class is as sure as its share of the entity's pixels; a reconstructed count is what was built.
    Layers below ``min_trust`` aren't read.
    """
    city = entities.select(F.col("entity_id").alias("_c"), "city")
    parts = []
    if min_trust is None or TRUST["pred"] >= min_trust:
        total = predicted.groupBy(F.col("entity_id").alias("_t")).agg(F.sum("pixels").alias("all"))
        parts.append(predicted.join(total, F.col("entity_id") == F.col("_t")).select("entity_id", F.lit("material").alias("attr"), F.lit("pred").alias("source"), (F.col("pixels") / F.col("all")).alias("confidence"), F.col("cls").alias("value")))
    if min_trust is None or TRUST["recon"] >= min_trust:
        for attr in ("windows", "doors"):
            parts.append(recon.select("entity_id", F.lit(attr).alias("attr"), F.lit("recon").alias("source"), F.lit(1.0).alias("confidence"), F.col(attr).cast("string").alias("value")))
    if not parts:
        return entities.limit(0).select("entity_id", "city", *[F.lit("").alias(c) for c in ("attr", "source", "value")], F.lit(0).alias("trust"), F.lit(0.0).alias("confidence"))
    out = reduce(DataFrame.unionByName, parts).join(city, F.col("entity_id") == F.col("_c")).drop("_c").withColumn("trust", trust_of(F.col("source")))
    return out if min_conf is None else out.where(F.col("confidence") >= min_conf)


def resolve_value(facts: DataFrame, policy: str = "authoritative_first") -> DataFrame:
    """One value an entity: ``authoritative_first`` (then best confidence), ``authoritative_only``, ``highest_confidence``, or ``none`` (all facts)."""
    if policy == "none":
        return facts
    if policy == "authoritative_only":
        facts, key = facts.where("source = 'auth'"), F.struct("confidence", "value")
    elif policy == "highest_confidence":
        key = F.struct("confidence", "trust", "value")
    elif policy == "authoritative_first":
        key = F.struct("trust", "confidence", "value")
    else:
        raise ValueError(policy)
    return facts.groupBy("entity_id", "city").agg(F.max_by("value", key).alias("value"), F.max_by("source", key).alias("source"))


def agreement(auth: Column, crowd: Column, tolerance: float) -> Column:
    """agree, disagree, auth_only, crowd_only or neither."""
    return F.when(auth.isNotNull() & crowd.isNotNull(), F.when(F.abs(auth - crowd) <= tolerance, "agree").otherwise("disagree")).when(auth.isNotNull(), "auth_only").when(crowd.isNotNull(), "crowd_only").otherwise("neither")


def coverage_agg(df: DataFrame, by: list[str], value: str, fn=F.avg, *, min_coverage: float | None = None) -> DataFrame:
    """The aggregate over covered rows beside how many are covered; below ``min_coverage`` the value is null and the status insufficient."""
    out = df.groupBy(*by).agg(fn(value).alias("value"), F.count(value).alias("covered"), F.count(F.lit(1)).alias("total"))
    out = out.withColumn("coverage", F.round(F.col("covered") / F.col("total"), 6))
    if min_coverage is None:
        return out
    enough = F.col("covered") / F.col("total") >= min_coverage
    return out.withColumns({"status": F.when(enough, "ok").otherwise("insufficient"), "value": F.when(enough, F.col("value"))})


def tri_state(covered: Column, value: Column) -> Column:
    """present, known_false or unavailable: what isn't covered is not false."""
    return F.when(~F.coalesce(covered, F.lit(False)), "unavailable").when(F.coalesce(value, F.lit(False)), "present").otherwise("known_false")


def co_missing(df: DataFrame, a: Column, b: Column) -> DataFrame:
    """Contingency of two layers' presence, with the phi coefficient."""
    n = lambda x, y: F.sum((x & y).cast("long"))
    out = df.agg(n(a, b).alias("both"), n(a, ~b).alias("only_a"), n(~a, b).alias("only_b"), n(~a, ~b).alias("neither"))
    p, q, r, s = (F.col(c).cast("double") for c in ("both", "only_a", "only_b", "neither"))
    root = F.sqrt((p + q) * (r + s) * (p + r) * (q + s))
    return out.withColumn("phi", F.when(root > 0, F.round((p * s - q * r) / root, 6)))


def attach_distribution(entities: DataFrame, predicted: DataFrame) -> DataFrame:
    """Entities with the whole predicted distribution (a map) and its pixels; null where nothing is predicted."""
    dist = predicted.groupBy("entity_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("cls", "pixels")))).alias("pred_dist"), F.sum("pixels").alias("pred_pixels"))
    return entities.join(dist.withColumnRenamed("entity_id", "_e"), F.col("entity_id") == F.col("_e"), "left").drop("_e")


def dominant(predicted: DataFrame) -> DataFrame:
    """The class with most pixels (ties to the first by name), its share and the distribution's entropy in bits."""
    best = predicted.groupBy("entity_id").agg(F.min(F.struct((-F.col("pixels")).alias("m"), "cls")).alias("b"), F.sum("pixels").alias("pixels"), F.collect_list(F.col("pixels").cast("double")).alias("all"))
    share = F.transform("all", lambda x: x / F.col("pixels"))
    entropy = F.aggregate(F.array_sort(share), F.lit(0.0), lambda a, x: a - x * F.log2(x))
    return best.select("entity_id", F.col("b.cls").alias("cls"), F.round(-F.col("b.m") / F.col("pixels"), 6).alias("share"), F.round(entropy, 6).alias("entropy"), "pixels")


def openings(recon: DataFrame) -> DataFrame:
    """One node per opening of the reconstructed objects."""
    kinds = F.array(F.struct(F.lit("window").alias("kind"), F.col("windows").alias("n")), F.struct(F.lit("door").alias("kind"), F.col("doors").alias("n")))
    rows = recon.withColumn("k", F.explode(kinds)).where("k.n > 0").withColumn("ring", F.explode(F.sequence(F.lit(1).cast("long"), F.col("k.n"))))
    return rows.select("entity_id", "recon_id", F.col("k.kind").alias("kind"), "ring")
