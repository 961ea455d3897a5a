"""Layers of the experiment graph over the given tables, by integer rules (see FIXTURES.md)."""
from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

CITIES = 5
DEEP_CITY = 3


def box(x0: Column, y0: Column, w: Column, h: Column) -> dict[str, Column]:
    return {"x0": x0, "y0": y0, "x1": x0 + w, "y1": y0 + h}


def _corners(*points: tuple[Column, Column]) -> Column:
    return F.array(*[F.struct(x.cast("long").alias("x"), y.cast("long").alias("y")) for x, y in points])


def shaped(df: DataFrame, kind: Column) -> DataFrame:
    """``df`` with ``rings`` and the footprint's ``area``: the box less a part (cx0, cy0, cx1, cy1).

    Kind 0: the upper right quarter is missing; 1: a hole; 2: the lower left ninth is missing; else the whole box.
    """
    w, h = F.col("x1") - F.col("x0"), F.col("y1") - F.col("y0")
    part = lambda v, size, lo, hi: (F.col(v) + lo(size), F.col(v) + hi(size))
    div = lambda k: lambda size: F.floor(size / k)
    zero, full = (lambda size: F.lit(0)), (lambda size: size)
    span = {0: (div(2), full), 1: (div(4), lambda size: F.floor(size / 4) + F.floor(size / 3)), 2: (zero, div(3))}
    pick = lambda v, size, i: F.coalesce(*[F.when(kind == k, part(v, size, *s)[i]) for k, s in span.items()], F.col(v))
    df = df.withColumns({"cx0": pick("x0", w, 0), "cy0": pick("y0", h, 0), "cx1": pick("x0", w, 1), "cy1": pick("y0", h, 1)})
    x0, y0, x1, y1, cx0, cy0, cx1, cy1 = (F.col(c) for c in ("x0", "y0", "x1", "y1", "cx0", "cy0", "cx1", "cy1"))
    box_ring = _corners((x0, y0), (x1, y0), (x1, y1), (x0, y1))
    rings = (
        F.when(kind == 0, F.array(_corners((x0, y0), (x1, y0), (x1, cy0), (cx0, cy0), (cx0, y1), (x0, y1))))
        .when(kind == 1, F.array(box_ring, _corners((cx0, cy0), (cx1, cy0), (cx1, cy1), (cx0, cy1))))
        .when(kind == 2, F.array(_corners((cx1, y0), (x1, y0), (x1, y1), (x0, y1), (x0, cy1), (cx1, cy1))))
        .otherwise(F.array(box_ring))
    )
    return df.withColumns({"rings": rings, "area": w * h - (cx1 - cx0) * (cy1 - cy0)})


@dataclass
class Layers:
    """Lazy DataFrames of one scale directory."""

    spark: SparkSession
    folder: str

    def table(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.folder}/{name}.parquet")

    @cached_property
    def entity(self) -> DataFrame:
        """Authoritative entities: box, storeys, classes, and thematic attributes that only some cities have."""
        nation = F.broadcast(self.table("nation").select("n_nationkey", "n_regionkey"))
        base = self.table("customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
        k, city = F.col("entity_id"), F.col("city")
        base = base.select(F.col("c_custkey").alias("entity_id"), F.col("n_regionkey").alias("city"), F.col("n_nationkey").alias("district"), "c_acctbal", F.col("c_mktsegment").alias("function"))
        base = base.withColumns(box((k % 64) * 400 + (k * 37) % 120, F.expr("(entity_id div 64) * 400") + (k * 53) % 120, 240 + (k * 29) % 360, 240 + (k * 31) % 360))
        base = base.withColumns({"tx": F.expr("(entity_id % 64) div 8"), "ty": F.expr("(entity_id div 64) div 4")})
        base = base.withColumn("storeys", 1 + (2 * F.col("tx") + 3 * F.col("ty") + city) % 9 + k % 3)
        base = base.withColumn("latent", (280 + 10 * city) * F.col("storeys") + (k * 17) % 121 - 60)
        area = (F.col("x1") - F.col("x0")) * (F.col("y1") - F.col("y0"))
        return base.withColumns(
            {
                "area": area,
                "auth_height": F.when((city != 1) & (F.col("c_acctbal") >= 0), F.col("latent")),
                "roof": F.when(city.isin(3, 4), (F.col("tx") + 2 * F.col("ty") + (k % 10 == 0).cast("int")) % 3),
                "floor_area": F.when((city == 4) & (k % 4 != 0), F.floor(area * F.col("storeys") / 10000)),
                "volume": F.when(city == 4, F.floor(area * F.col("latent") / 1000000)),
                "year_built": F.when(city == 4, 1900 + (k * 7) % 120),
                "vintage": F.when(city == 0, 2015 + k % 10),
                "用途": F.when(city == 2, F.element_at(F.array(F.lit("住宅"), F.lit("商業"), F.lit("工業")), (k % 3 + 1).cast("int"))),
                "構造": F.when((city == 2) & (k % 2 == 0), F.lit("木造")),
            }
        )

    @cached_property
    def crowd(self) -> DataFrame:
        """Crowd-sourced features; their owner is hidden from the matcher."""
        orders = self.table("orders").where("o_orderpriority = '1-URGENT'").select("o_orderkey", "o_custkey", "o_orderstatus", "o_orderdate")
        own = self.entity.select(F.col("entity_id").alias("owner"), "city", F.col("x0").alias("ox"), F.col("y0").alias("oy"), "storeys", "latent")
        o = F.col("o_orderkey")
        rows = orders.join(own, F.col("o_custkey") == F.col("owner"))
        rows = rows.withColumns(box(F.col("ox") + (o * 41) % 200 - 100, F.col("oy") + (o * 43) % 200 - 100, 120 + (o * 47) % 600, 120 + (o * 59) % 600))
        rows = rows.withColumns(
            {
                "feature_id": o,
                "area": (F.col("x1") - F.col("x0")) * (F.col("y1") - F.col("y0")),
                "levels": F.col("storeys") + (o % 11 == 0).cast("int"),
                "crowd_height": F.when(o % 5 != 0, F.col("latent") + (o * 61) % 201 - 100 + 900 * (o % 17 == 0).cast("int")),
                "tags": F.create_map(F.lit("status"), F.col("o_orderstatus"), F.lit("dated"), F.col("o_orderdate").cast("date").cast("string")),
            }
        )
        return rows.select("feature_id", "city", "x0", "y0", "x1", "y1", "area", "levels", "crowd_height", F.col("o_orderstatus").alias("status"), "tags")

    @property
    def entity_shapes(self) -> DataFrame:
        """Entities with footprints: L-shapes, boxes with a hole, boxes."""
        return shaped(self.entity.select("city", "entity_id", "x0", "y0", "x1", "y1"), F.when(F.col("entity_id") % 3 < 2, F.col("entity_id") % 3).otherwise(3))

    @property
    def crowd_shapes(self) -> DataFrame:
        """Crowd features with footprints: L-shapes and boxes."""
        return shaped(self.crowd.select("city", "feature_id", "x0", "y0", "x1", "y1"), F.when(F.col("feature_id") % 2 == 0, 2).otherwise(3))

    @cached_property
    def predicted(self) -> DataFrame:
        """Predicted classes with pixel counts, for part of one city."""
        orders = self.table("orders").where("o_orderpriority = '5-LOW'").select("o_orderkey", "o_custkey")
        lines = self.table("lineitem").where("l_returnflag = 'R' and l_linenumber <= 2").select("l_orderkey", "l_partkey", "l_quantity")
        deep = self.entity.where(F.col("city") == DEEP_CITY).select("entity_id")
        rows = orders.join(deep, F.col("o_custkey") == F.col("entity_id")).join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
        rows = rows.join(self.table("part").select("p_partkey", F.col("p_type").alias("cls")), F.col("l_partkey") == F.col("p_partkey"))
        return rows.groupBy("entity_id", "cls").agg(F.sum("l_quantity").cast("long").alias("pixels"))

    @cached_property
    def recon(self) -> DataFrame:
        """Reconstructed objects with their openings."""
        deep = self.entity.where((F.col("city") == DEEP_CITY) & (F.col("entity_id") % 4 == 0)).select("entity_id")
        n = lambda p: F.size(F.regexp_extract_all("html", F.lit(p), F.lit(0))).cast("long")
        return self.table("pages").join(deep, F.col("page_id") == F.col("entity_id")).select("entity_id", F.col("page_id").alias("recon_id"), n("<a[ >]").alias("windows"), n("<p[ >]").alias("doors"))

    @cached_property
    def poi(self) -> DataFrame:
        """Points of interest."""
        nation = F.broadcast(self.table("nation").select("n_nationkey", "n_regionkey"))
        s = F.col("s_suppkey")
        rows = self.table("supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey"))
        return rows.select(s.alias("poi_id"), F.col("n_regionkey").alias("city"), ((s * 15) % 64 * 400 + (s * 71) % 400).alias("x"), (F.expr("(s_suppkey * 15) div 64") * 400 + (s * 83) % 400).alias("y"))


#: The same rules as SQL for the oracle.
ENTITY_SQL = """entity as (select *, (x1 - x0) * (y1 - y0) area,
  case when city <> 1 and c_acctbal >= 0 then latent end auth_height,
  case when city in (3, 4) then (tx + 2 * ty + (case when k % 10 = 0 then 1 else 0 end)) % 3 end roof,
  case when city = 4 and k % 4 <> 0 then (x1 - x0) * (y1 - y0) * storeys // 10000 end floor_area,
  case when city = 4 then (x1 - x0) * (y1 - y0) * latent // 1000000 end volume,
  case when city = 4 then 1900 + (k * 7) % 120 end year_built,
  case when city = 0 then 2015 + k % 10 end vintage,
  case when city = 2 then (case k % 3 when 0 then '住宅' when 1 then '商業' else '工業' end) end "用途",
  case when city = 2 and k % 2 = 0 then '木造' end "構造"
 from (select *, (280 + 10 * city) * storeys + (k * 17) % 121 - 60 latent from (select *, 1 + (2 * tx + 3 * ty + city) % 9 + k % 3 storeys from (
  select c_custkey k, c_custkey entity_id, n_regionkey city, n_nationkey district, c_acctbal, c_mktsegment "function",
   (k % 64) * 400 + (k * 37) % 120 x0, (k // 64) * 400 + (k * 53) % 120 y0,
   (k % 64) * 400 + (k * 37) % 120 + 240 + (k * 29) % 360 x1, (k // 64) * 400 + (k * 53) % 120 + 240 + (k * 31) % 360 y1,
   (k % 64) // 8 tx, (k // 64) // 4 ty from customer join nation on c_nationkey = n_nationkey))))"""
CROWD_SQL = """crowd as (select *, (x1 - x0) * (y1 - y0) area from (select o feature_id, city, ox + (o * 41) % 200 - 100 x0, oy + (o * 43) % 200 - 100 y0,
  ox + (o * 41) % 200 - 100 + 120 + (o * 47) % 600 x1, oy + (o * 43) % 200 - 100 + 120 + (o * 59) % 600 y1,
  storeys + (case when o % 11 = 0 then 1 else 0 end) levels,
  case when o % 5 <> 0 then latent + (o * 61) % 201 - 100 + 900 * (case when o % 17 = 0 then 1 else 0 end) end crowd_height, status
 from (select o_orderkey o, city, e.x0 ox, e.y0 oy, storeys, latent, o_orderstatus status from orders join entity e on o_custkey = entity_id where o_orderpriority = '1-URGENT')))"""
EDGE_SQL = """cand as (select a.city, a.entity_id, b.feature_id, a.area area_a, b.area area_b,
  (least(a.x1, b.x1) - greatest(a.x0, b.x0)) * (least(a.y1, b.y1) - greatest(a.y0, b.y0)) shared
 from entity a join crowd b on a.city = b.city and a.x0 < b.x1 and b.x0 < a.x1 and a.y0 < b.y1 and b.y0 < a.y1),
edge as (select *, shared::double / least(area_a, area_b) overlap, shared::double / (area_a + area_b - shared) jaccard from cand where 10 * shared >= 3 * least(area_a, area_b))"""
PREDICTED_SQL = """predicted as (select entity_id, p_type cls, sum(l_quantity)::bigint pixels from orders join entity on o_custkey = entity_id join lineitem on o_orderkey = l_orderkey join part on l_partkey = p_partkey
 where o_orderpriority = '5-LOW' and city = 3 and l_returnflag = 'R' and l_linenumber <= 2 group by 1, 2)"""
RECON_SQL = """recon as (select entity_id, page_id recon_id, len(regexp_extract_all(html, '<a[ >]'))::bigint windows, len(regexp_extract_all(html, '<p[ >]'))::bigint doors
 from pages join entity on page_id = entity_id where city = 3 and entity_id % 4 = 0)"""
POI_SQL = """poi as (select s_suppkey poi_id, n_regionkey city, (s_suppkey * 15) % 64 * 400 + (s_suppkey * 71) % 400 x, (s_suppkey * 15) // 64 * 400 + (s_suppkey * 83) % 400 y
 from supplier join nation on s_nationkey = n_nationkey)"""


def sql(body: str, *more: str) -> str:
    """``body`` over all layers."""
    return "with recursive " + ",\n".join([ENTITY_SQL, CROWD_SQL, EDGE_SQL, PREDICTED_SQL, RECON_SQL, POI_SQL, *more]) + "\n" + body
