"""The labelled property graph: nodes and edges of all layers, tiers, statistics, integrity, and traversal."""
from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from provgraph.functions.durable import cut
from provgraph.functions.geometry import polygon_area
from provgraph.operators import fusion, provenance
from provgraph.sources.overlay import Layers


@dataclass
class PropertyGraph:
    """nodes: city, layer, kind, node_id, trust, x0, y0, x1, y1, attrs.  edges: city, kind, src, dst, overlap, jaccard."""

    nodes: DataFrame
    edges: DataFrame

    @classmethod
    def from_layers(cls, layers: Layers) -> PropertyGraph:
        box = ["x0", "y0", "x1", "y1"]

        def nodes(df, layer, kind, ident, attrs: dict[str, Column]):
            for c in box:
                if c not in df.columns:
                    df = df.withColumn(c, F.lit(None).cast("long"))
            pairs = [x for k, v in attrs.items() for x in (F.lit(k), v.cast("string"))]
            kept = F.map_filter(F.create_map(*pairs), lambda k, v: v.isNotNull())
            return df.select("city", F.lit(layer).alias("layer"), F.lit(kind).alias("kind"), F.col(ident).alias("node_id"), provenance.trust_of(F.lit(layer)).alias("trust"), *box, kept.alias("attrs"))

        own = ["storeys", "auth_height", "roof", "function", "floor_area", "volume", "year_built", "vintage", "用途", "構造"]
        deep = layers.entity.select("entity_id", "city")
        recon, pred = layers.recon.join(deep, "entity_id"), layers.predicted.join(deep, "entity_id")
        edge = fusion.edges(fusion.candidates(layers.entity, layers.crowd))
        all_nodes = [
            nodes(layers.entity, "auth", "entity", "entity_id", {c: F.col(c) for c in own}),
            nodes(layers.crowd, "crowd", "feature", "feature_id", {"levels": F.col("levels"), "crowd_height": F.col("crowd_height"), "status": F.col("status")}),
            nodes(recon, "recon", "facade", "recon_id", {"windows": F.col("windows"), "doors": F.col("doors")}),
            nodes(pred, "pred", "class", "entity_id", {"cls": F.col("cls"), "pixels": F.col("pixels")}),
        ]
        link = lambda df, kind, dst: df.select("city", F.lit(kind).alias("kind"), F.col("entity_id").alias("src"), F.col(dst).alias("dst"), F.lit(None).cast("double").alias("overlap"), F.lit(None).cast("double").alias("jaccard"))
        fused = edge.select("city", F.lit("fusion").alias("kind"), F.col("entity_id").alias("src"), F.col("feature_id").alias("dst"), "overlap", "jaccard")
        return cls(reduce(DataFrame.unionByName, all_nodes), reduce(DataFrame.unionByName, [fused, link(recon, "facade", "recon_id"), link(pred, "material", "entity_id")]))

    def with_external(self, rows: DataFrame, layer: str, kind: str, ident: str, attrs: list[str], links: DataFrame | None = None) -> PropertyGraph:
        """The graph and the objects of a further source: each is a node of its own, with its id, box (if ``rows`` has one) and attributes.

        ``links`` (city, src, dst, jaccard) ties them to entities; nothing that is there already changes.
        """
        if layer == "auth":
            raise ValueError("the authoritative layer is not external")
        box = [F.col(c).cast("long").alias(c) if c in rows.columns else F.lit(None).cast("long").alias(c) for c in ("x0", "y0", "x1", "y1")]
        pairs = [x for a in attrs for x in (F.lit(a), F.col(a).cast("string"))]
        kept = F.map_filter(F.create_map(*pairs), lambda k, v: v.isNotNull())
        nodes = rows.select("city", F.lit(layer).alias("layer"), F.lit(kind).alias("kind"), F.col(ident).alias("node_id"), F.coalesce(provenance.trust_of(F.lit(layer)), F.lit(0)).alias("trust"), *box, kept.alias("attrs"))
        edges = self.edges
        if links is not None:
            edges = edges.unionByName(links.select("city", F.lit(kind).alias("kind"), "src", "dst", F.lit(None).cast("double").alias("overlap"), "jaccard"))
        return PropertyGraph(self.nodes.unionByName(nodes), edges)

    def tier(self, n: int) -> PropertyGraph:
        """Tier 1: the two layers that every city has.  Tier 2: all four."""
        if n == 2:
            return self
        return PropertyGraph(self.nodes.where(F.col("layer").isin("auth", "crowd")), self.edges.where("kind = 'fusion'"))

    def availability(self) -> DataFrame:
        """City by layer: number of nodes, 0 where the layer is absent."""
        return self.nodes.groupBy("city").pivot("layer", ["auth", "crowd", "pred", "recon"]).agg(F.count(F.lit(1))).na.fill(0)

    def invariants(self) -> DataFrame:
        """(name, violations): no overwriting of authoritative values, identity of external nodes, confidence of fusion edges, one trust class a fact."""
        # The authoritative layer's own keys, a few dozen by schema: no other layer may bring a value under one of them.
        own = [r[0] for r in self.nodes.where("layer = 'auth'").select(F.explode(F.map_keys("attrs")).alias("k")).distinct().collect()]
        n = self.nodes.agg(
            F.sum(((F.col("layer") != "auth") & F.arrays_overlap(F.map_keys("attrs"), F.array(*map(F.lit, own)).cast("array<string>"))).cast("long")).alias("no_overwrite"),
            F.sum(((F.col("layer") != "auth") & F.col("node_id").isNull()).cast("long")).alias("external_identity"),
            F.sum(F.col("trust").isNull().cast("long")).alias("one_trust_class"),
        )
        e = self.edges.where("kind = 'fusion'").agg(F.sum(F.coalesce(~((F.col("jaccard") > 0) & (F.col("jaccard") <= 1)), F.lit(True)).cast("long")).alias("edge_confidence"))
        long = lambda df: df.select(F.explode(F.array(*[F.struct(F.lit(c).alias("name"), F.coalesce(c, F.lit(0)).cast("long").alias("violations")) for c in df.columns])).alias("r")).select("r.*")
        return long(n).union(long(e))

    def checks(self) -> DataFrame:
        """(name, expected, actual, ok): after ingest, unique ids, edges that meet nodes, boxes in the index, known layers."""
        ids = self.nodes.where("layer <> 'pred'").agg(F.count(F.lit(1)).alias("expected"), F.countDistinct("layer", "node_id").alias("actual")).select(F.lit("unique_ids").alias("name"), "*")
        fused = self.edges.where("kind = 'fusion'")
        both = fused.join(self.nodes.where("layer = 'auth'").select(F.col("node_id").alias("a")), F.col("src") == F.col("a"), "left_semi").join(self.nodes.where("layer = 'crowd'").select(F.col("node_id").alias("b")), F.col("dst") == F.col("b"), "left_semi")
        ends = fused.agg(F.count(F.lit(1)).alias("expected")).crossJoin(both.agg(F.count(F.lit(1)).alias("actual"))).select(F.lit("edge_ends").alias("name"), "*")
        spatial = self.nodes.where(F.col("layer").isin("auth", "crowd")).agg(F.count(F.lit(1)).alias("expected"), F.sum(((F.col("x1") > F.col("x0")) & (F.col("y1") > F.col("y0"))).cast("long")).alias("actual")).select(F.lit("spatial_coverage").alias("name"), "*")
        known = self.nodes.agg(F.count(F.lit(1)).alias("expected"), F.count("trust").alias("actual")).select(F.lit("provenance_complete").alias("name"), "*")
        return reduce(DataFrame.unionByName, [ids, ends, spatial, known]).withColumn("ok", F.col("expected") == F.col("actual"))


def validate_boxes(df: DataFrame, ident: str, *, span: int = 10_000_000) -> DataFrame:
    """(rule, id): null or repeated ids, null, empty or inverted boxes, coordinates out of range; one scan beside the count of ids."""
    flat = (F.col("x1") <= F.col("x0")) | (F.col("y1") <= F.col("y0"))
    far = F.greatest(F.abs("x0"), F.abs("y0"), F.abs("x1"), F.abs("y1")) > span
    absent = F.col("x0").isNull() | F.col("y0").isNull() | F.col("x1").isNull() | F.col("y1").isNull()
    rules = {"null_id": F.col(ident).isNull(), "null_geometry": absent, "degenerate_geometry": flat, "out_of_range": far}
    found = F.array_compact(F.array(*[F.when(c, F.lit(n)) for n, c in rules.items()]))
    rows = df.select(F.explode(found).alias("rule"), F.col(ident).alias("id"))
    repeated = df.where(F.col(ident).isNotNull()).groupBy(F.col(ident).alias("id")).count().where("count > 1").select(F.lit("duplicate_id").alias("rule"), "id")
    return rows.union(repeated)


def validate_rings(df: DataFrame, ident: str, *, rings: str = "rings", crs: str | None = None, expected: str | None = None) -> DataFrame:
    """(rule, id): unclosed rings (fewer than three corners, or an end that isn't the start), rings that cross themselves, no area, another CRS.

    A ring is closed where its last corner repeats the first; null rings are null geometry.  Crossing is tested
    between all segments of a ring that don't touch, with whole or decimal coordinates.
    """
    ends = lambda r: (F.element_at(r, 1)["x"] == F.element_at(r, -1)["x"]) & (F.element_at(r, 1)["y"] == F.element_at(r, -1)["y"])
    unclosed = F.exists(rings, lambda r: (F.size(r) < 4) | ~ends(r))

    def crosses(r: Column) -> Column:
        seg = F.transform(F.sequence(F.lit(1), F.greatest(F.size(r) - 1, F.lit(1))), lambda i: F.struct(i.alias("i"), F.get(r, i - 1).alias("a"), F.get(r, i).alias("b")))
        turn = lambda a, b, c: F.signum((b["x"] - a["x"]) * (c["y"] - a["y"]) - (b["y"] - a["y"]) * (c["x"] - a["x"]))
        apart = lambda s, t: (t["i"] > s["i"] + 1) & ~((s["i"] == 1) & (t["i"] == F.size(r) - 1))
        cut = lambda s, t: (turn(s["a"], s["b"], t["a"]) * turn(s["a"], s["b"], t["b"]) < 0) & (turn(t["a"], t["b"], s["a"]) * turn(t["a"], t["b"], s["b"]) < 0)
        return F.exists(seg, lambda s: F.exists(seg, lambda t: apart(s, t) & cut(s, t)))

    rules = {"null_geometry": F.col(rings).isNull(), "unclosed_ring": unclosed, "crossing_ring": F.exists(rings, crosses), "zero_area": F.coalesce(polygon_area(F.col(rings)) <= 0, F.lit(False))}
    if crs:
        rules["wrong_crs"] = ~F.col(crs).eqNullSafe(F.lit(expected))
    found = F.array_compact(F.array(*[F.when(c, F.lit(n)) for n, c in rules.items()]))
    return df.select(F.explode(found).alias("rule"), F.col(ident).alias("id"))


class Match:
    """A path pattern over typed edges: ``Match(g).node('auth').edge('fusion').node('crowd', where)``; a chain of equi-joins."""

    def __init__(self, graph: PropertyGraph):
        self.graph, self.rows, self.n, self.pending = graph, None, 0, None

    def node(self, layer: str, where: Column | None = None) -> Match:
        name = f"n{self.n}"
        side = self.graph.nodes.where(F.col("layer") == layer)
        side = side if where is None else side.where(where)
        side = side.select(F.col("node_id").alias(name), F.col("attrs").alias(f"{name}_attrs"), F.col("city").alias(f"{name}_city"))
        if self.pending is None:
            self.rows = side
        else:
            kind, out = self.pending
            a, b = ("src", "dst") if out else ("dst", "src")
            e = self.graph.edges.where(F.col("kind") == kind).select(F.col(a).alias("_a"), F.col(b).alias("_b"))
            self.rows = self.rows.join(e, F.col(f"n{self.n - 1}") == F.col("_a")).drop("_a").join(side, F.col("_b") == F.col(name)).drop("_b")
        self.n += 1
        return self

    def edge(self, kind: str, out: bool = True) -> Match:
        self.pending = (kind, out)
        return self

    def where(self, condition: Column) -> Match:
        self.rows = self.rows.where(condition)
        return self


def hops(edges: DataFrame, seeds: DataFrame, most: int) -> DataFrame:
    """(node, hop): nodes at most ``most`` undirected steps from the seeds, with the least number of steps.  edges: src, dst; seeds: node."""
    both = cut(edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct())
    seen = cut(seeds.select("node").distinct().withColumn("hop", F.lit(0)))
    front = seen
    for h in range(1, most + 1):
        near = front.join(both, F.col("node") == F.col("src")).select(F.col("dst").alias("node")).distinct()
        front = cut(near.join(seen.select(F.col("node").alias("_n")), F.col("node") == F.col("_n"), "left_anti").withColumn("hop", F.lit(h)))
        if front.isEmpty():
            break
        seen = cut(seen.union(front))
    return seen
