"""Sources, sinks, and the Arrow function surface."""
from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from provgraph.functions.durable import checkpoint_folder
from provgraph.functions.geometry import polygon_area, polygon_overlap_area
from provgraph.operators import fusion
from provgraph.operators.graph import PropertyGraph
from provgraph.plans.registry import workload
from provgraph.sources.overlay import Layers, sql

#: Files of one exported folder at most (more where Spark's own limits split them).
FILES = 16
FORMATS = ("parquet", "csv", "json", "orc")


def folder(spark: SparkSession) -> str:
    return f"{checkpoint_folder(spark)}/files-{uuid.uuid4().hex}"


def write(df: DataFrame, path: str, kind: str, **options) -> None:
    writer = df.write.format(kind).options(**options)
    (writer.option("header", True) if kind == "csv" else writer).save(path)


def read(spark: SparkSession, path: str, kind: str, schema) -> DataFrame:
    """With an explicit schema: nothing is inferred."""
    reader = spark.read.format(kind).schema(schema)
    return (reader.option("header", True) if kind == "csv" else reader).load(path)


def write_graph(g: PropertyGraph, path: str) -> None:
    """A neutral node and edge export, one folder a city and layer or kind; each is written by up to FILES tasks, however large it is."""
    lot = lambda *c: F.pmod(F.xxhash64(*c), F.lit(FILES))
    g.nodes.repartition("city", "layer", lot("node_id")).write.partitionBy("city", "layer").parquet(f"{path}/nodes")
    g.edges.repartition("city", "kind", lot("src", "dst")).write.partitionBy("city", "kind").parquet(f"{path}/edges")


def read_graph(spark: SparkSession, path: str) -> PropertyGraph:
    return PropertyGraph(spark.read.parquet(f"{path}/nodes"), spark.read.parquet(f"{path}/edges"))


for _kind in FORMATS:

    def _round_trip(spark, d, kind=_kind):
        c = Layers(spark, d).table("customer")
        write(c, path := folder(spark), kind)
        return read(spark, path, kind, c.schema)

    workload(f"io_roundtrip_{_kind}", "select c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment from customer")(_round_trip)


@workload("io_graph_export", "select layer, count(*)::bigint nodes from (select 'auth' layer from customer union all select 'crowd' from orders where o_orderpriority = '1-URGENT') group by 1")
def io_graph_export(spark, d):
    g = PropertyGraph.from_layers(Layers(spark, d)).tier(1)
    write_graph(g, path := folder(spark))
    return read_graph(spark, path).nodes.groupBy("layer").agg(F.count(F.lit(1)).alias("nodes"))


@workload("graph_sizes")
def graph_sizes(spark, d):
    """MB of the graph's nodes per city and layer: as a store (columnar) and as a dump (compressed lines)."""
    g = PropertyGraph.from_layers(Layers(spark, d))
    write_graph(g, path := folder(spark))
    lines = g.nodes.withColumn("attrs", F.to_json("attrs"))
    lines.repartition("city", "layer", F.pmod(F.xxhash64("node_id"), F.lit(FILES))).write.partitionBy("city", "layer").option("compression", "gzip").json(f"{path}/dump")
    files = lambda df: df.select("city", "layer", "_metadata.file_path", "_metadata.file_size").distinct().groupBy("city", "layer").agg((F.sum("file_size") / 1e6).alias("mb"))
    store, dump = files(spark.read.parquet(f"{path}/nodes")), files(spark.read.schema(lines.schema).json(f"{path}/dump"))
    return store.select("city", "layer", F.col("mb").alias("store_mb")).join(dump.select("city", "layer", F.col("mb").alias("dump_mb")), ["city", "layer"])


def _rings(x0, y0, x1, y1):
    p = lambda x, y: F.struct(F.col(x).cast("double").alias("x"), F.col(y).cast("double").alias("y"))
    return F.array(F.array(p(x0, y0), p(x1, y0), p(x1, y1), p(x0, y1)))


@workload("udf_polygon_area", "select c_custkey entity_id, ((240 + (c_custkey * 29) % 360) * (240 + (c_custkey * 31) % 360))::double area from customer")
def udf_polygon_area(spark, d):
    return Layers(spark, d).entity.select("entity_id", polygon_area(_rings("x0", "y0", "x1", "y1")).alias("area"))


@workload("udf_polygon_overlap", sql("select entity_id, feature_id, shared::bigint shared, shared::double clipped from cand"))
def udf_polygon_overlap(spark, d):
    """General clipping on box rings: must equal the whole-number box measure."""
    w = Layers(spark, d)
    a = w.entity.select("entity_id", _rings("x0", "y0", "x1", "y1").alias("ra"))
    b = w.crowd.select("feature_id", _rings("x0", "y0", "x1", "y1").alias("rb"))
    rows = fusion.candidates(w.entity, w.crowd).select("entity_id", "feature_id", "shared").join(a, "entity_id").join(b, "feature_id")
    return rows.select("entity_id", "feature_id", F.col("shared").cast("long").alias("shared"), F.round(polygon_overlap_area("ra", "rb"), 3).alias("clipped"))


@workload("udf_mapinpandas", "select o_orderkey, round(ln(o_totalprice), 6) logged from orders")
def udf_mapinpandas(spark, d):
    import numpy as np

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame({"o_orderkey": pdf["o_orderkey"], "logged": np.log(pdf["o_totalprice"])})

    return Layers(spark, d).table("orders").select("o_orderkey", "o_totalprice").mapInPandas(run, "o_orderkey long, logged double").select("o_orderkey", F.round("logged", 6).alias("logged"))


_F1 = "r as (select city, roof c, (tx + 2 * ty) % 3 chat from entity where roof is not null)"


@workload("udf_grouped", sql("""select city::bigint city, round(avg(2.0 * tp / (2 * tp + fp + fn)), 9) macro_f1 from (select r.city, k.c, count(*) filter (where r.c = k.c and chat = k.c) tp, count(*) filter (where r.c <> k.c and chat = k.c) fp, count(*) filter (where r.c = k.c and chat <> k.c) fn
 from r join (select distinct city, c from r) k on r.city = k.city group by 1, 2) group by city""", _F1))
def udf_grouped(spark, d):
    """Macro-F1 as a grouped function over a confusion table that was counted before: a group is classes by classes rows."""

    def macro_f1(pdf: pd.DataFrame) -> pd.DataFrame:
        hit = pdf[pdf["c"] == pdf["chat"]].set_index("c")["n"]
        real, said = pdf.groupby("c")["n"].sum(), pdf.groupby("chat")["n"].sum()
        f1 = 2 * hit.reindex(real.index, fill_value=0) / (real + said.reindex(real.index, fill_value=0))
        return pd.DataFrame({"city": pdf["city"].iloc[:1], "macro_f1": [float(f1.mean())]})

    e = Layers(spark, d).entity.where("roof is not null").select(F.col("city").cast("long").alias("city"), F.col("roof").cast("int").alias("c"), ((F.col("tx") + 2 * F.col("ty")) % 3).cast("int").alias("chat"))
    out = e.groupBy("city", "c", "chat").agg(F.count(F.lit(1)).alias("n")).groupBy("city").applyInPandas(macro_f1, "city long, macro_f1 double")
    return out.select("city", F.round("macro_f1", 9).alias("macro_f1"))


@F.udtf(returnType=StructType([StructField("step", IntegerType()), StructField("length", LongType())]))
class Segments:
    """A box ring's segments: number and length of each."""

    def eval(self, x0: int, y0: int, x1: int, y1: int):
        ring = [(x0, y0), (x1, y0), (x1, y1), (x0, y1)]
        for i, (a, b) in enumerate(zip(ring, ring[1:] + ring[:1])):
            yield i, abs(a[0] - b[0]) + abs(a[1] - b[1])


@workload("udtf_segments", sql("select entity_id, step::int step, (case when step % 2 = 0 then x1 - x0 else y1 - y0 end)::bigint length from entity, (select unnest(range(4)) step)"))
def udtf_segments(spark, d):
    """A table function applied to every entity by a lateral join."""
    e = Layers(spark, d).entity.select("entity_id", *[F.col(c).cast("long").alias(c) for c in ("x0", "y0", "x1", "y1")])
    return e.lateralJoin(Segments(*[F.col(c).outer() for c in ("x0", "y0", "x1", "y1")])).select("entity_id", "step", "length")
