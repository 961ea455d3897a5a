"""Experiment workloads over the layered graph: statistics, identity, fusion, provenance, coverage, space."""
from __future__ import annotations

from pyspark.sql import functions as F

from provgraph.operators import fusion, graph, identity, provenance, spatial
from provgraph.plans.registry import workload
from provgraph.sources.overlay import Layers, sql

LONG = "long"
TAUS = [(i, 10) for i in range(1, 10)]
HOUR = 3600


def _edges(w: Layers):
    return fusion.edges(fusion.candidates(w.entity, w.crowd))


def long(*names):
    return [F.col(n).cast("long").alias(n) for n in names]


# --- dataset statistics -------------------------------------------------------------------------


@workload("overview_by_city", sql("""select city::bigint city, count(*)::bigint entities, sum(n_orders)::bigint orders, sum(n_lines)::bigint lines
 from (select e.city, e.entity_id, count(distinct o_orderkey) n_orders, count(l_orderkey) n_lines from entity e left join orders on o_custkey = entity_id left join lineitem on l_orderkey = o_orderkey group by 1, 2)
 group by grouping sets ((city), ())"""))
def overview_by_city(spark, d):
    w = Layers(spark, d)
    lines = w.table("lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))
    per = w.table("orders").select("o_orderkey", "o_custkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n_orders"), F.sum("n").alias("n_lines"))
    rows = w.entity.select("city", "entity_id").join(per, F.col("entity_id") == F.col("o_custkey"), "left")
    out = rows.groupingSets([["city"], []], "city").agg(F.count(F.lit(1)).alias("entities"), F.sum(F.coalesce("n_orders", F.lit(0))).alias("orders"), F.sum(F.coalesce("n_lines", F.lit(0))).alias("lines"))
    return out.select(*long("city", "entities", "orders", "lines"))


@workload("nodes_per_entity_median", sql("""select city::bigint city, median(n)::double median_nodes from (select city, entity_id, count(o_orderkey) n from entity left join orders on o_custkey = entity_id group by 1, 2) group by 1"""))
def nodes_per_entity_median(spark, d):
    w = Layers(spark, d)
    per = w.table("orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    rows = w.entity.select("city", "entity_id").join(per, F.col("entity_id") == F.col("o_custkey"), "left")
    return rows.groupBy(F.col("city").cast("long").alias("city")).agg(F.percentile(F.coalesce("n", F.lit(0)), F.lit(0.5)).alias("median_nodes"))


@workload("thematic_keys_by_city", sql("""select city::bigint city, count(*)::bigint thematic_keys from (
 select distinct city, key from (unpivot (select city, floor_area::varchar floor_area, volume::varchar volume, year_built::varchar year_built, vintage::varchar vintage, "用途", "構造" from entity) on floor_area, volume, year_built, vintage, "用途", "構造" into name key value v) where v is not null) group by 1"""))
def thematic_keys_by_city(spark, d):
    e = Layers(spark, d).entity
    keys = ["floor_area", "volume", "year_built", "vintage", "用途", "構造"]
    present = F.array_compact(F.array(*[F.when(F.col(k).isNotNull(), F.lit(k)) for k in keys]))
    return e.select(F.col("city").cast("long").alias("city"), F.explode(present).alias("k")).groupBy("city").agg(F.countDistinct("k").alias("thematic_keys"))


@workload("enrichment_share", sql("""select city::bigint city, count(m)::bigint matched, count(*)::bigint total, round(count(m) / count(*), 6) share
 from (select city, entity_id, case when entity_id in (select entity_id from edge) then 1 end m from entity) group by grouping sets ((city), ())"""))
def enrichment_share(spark, d):
    w = Layers(spark, d)
    return fusion.enrichment(w.entity, _edges(w)).select(*long("city", "matched", "total"), "share")


@workload("layer_availability", sql("""select city::bigint city, count(*) filter (where l = 'auth')::bigint auth, count(*) filter (where l = 'crowd')::bigint crowd, count(*) filter (where l = 'pred')::bigint pred, count(*) filter (where l = 'recon')::bigint recon
 from (select city, 'auth' l from entity union all select city, 'crowd' from crowd union all select 3, 'pred' from predicted union all select 3, 'recon' from recon) group by 1"""))
def layer_availability(spark, d):
    return graph.PropertyGraph.from_layers(Layers(spark, d)).availability().select(*long("city", "auth", "crowd", "pred", "recon"))


# --- identity and integrity ---------------------------------------------------------------------

_LINE = ["l_orderkey", "l_linenumber"]
_FLAGS = ["l_returnflag", "l_linestatus"]


@workload("dup_id_report", """with g as (select l_orderkey, l_linenumber, l_returnflag, l_linestatus, count(*) n from lineitem group by all), i as (select l_orderkey, l_linenumber, sum(n) n, count(*) v from g group by 1, 2)
 select sum(n)::bigint records, count(*) filter (where n > 1)::bigint duplicate_ids, sum(case when n > 1 then n else 0 end)::bigint records_affected, sum(n - v)::bigint merged_away, sum(v - 1)::bigint renamed, round(sum(case when n > 1 then n else 0 end)::double / sum(n), 6) share_of_input from i""")
def dup_id_report(spark, d):
    return identity.report(Layers(spark, d).table("lineitem"), _LINE, _FLAGS)


_HASH = """sha256('{"l_linestatus":"' || l_linestatus || '","l_returnflag":"' || l_returnflag || '"}')"""


def _resolved(spark, d, policy):
    rows = Layers(spark, d).table("lineitem").select(*_LINE, *_FLAGS)
    return identity.resolve(rows, _LINE, _FLAGS, policy=policy).select("old_id", "new_id", "reason", F.col("merged_n").cast("long").alias("merged_n"), *_FLAGS)


@workload("dup_id_resolved", f"""select old_id, case when v = 1 then old_id else old_id || '#' || v end new_id, case when v > 1 then 'renamed' when n > 1 then 'merged' else 'kept' end reason, n::bigint merged_n, l_returnflag, l_linestatus
 from (select old_id, l_returnflag, l_linestatus, n, dense_rank() over (partition by old_id order by h) v from (select l_orderkey || '-' || l_linenumber old_id, l_returnflag, l_linestatus, {_HASH} h, count(*) n from lineitem group by all))""")
def dup_id_resolved(spark, d):
    return _resolved(spark, d, "merge_or_rename")


@workload("dup_id_merge_only", f"""select old_id, old_id new_id, case when count(*) > 1 then 'merged' else 'kept' end reason, count(*)::bigint merged_n, arg_min(l_returnflag, h) l_returnflag, arg_min(l_linestatus, h) l_linestatus
 from (select l_orderkey || '-' || l_linenumber old_id, *, {_HASH} h from lineitem) group by 1""")
def dup_id_merge_only(spark, d):
    return _resolved(spark, d, "merge_only")


@workload("dup_id_rename_only", f"""select old_id, case when v = 1 then old_id else old_id || '#' || v end new_id, case when v > 1 then 'renamed' else 'kept' end reason, 1::bigint merged_n, l_returnflag, l_linestatus
 from (select l_orderkey || '-' || l_linenumber old_id, l_returnflag, l_linestatus, row_number() over (partition by l_orderkey, l_linenumber order by {_HASH}, l_returnflag, l_linestatus) v from lineitem)""")
def dup_id_rename_only(spark, d):
    return _resolved(spark, d, "rename_only")


@workload("boundary_duplicates", "select md5(text) content_md5, count(*)::bigint copies, count(distinct source)::bigint tiles from documents group by text having count(distinct source) > 1")
def boundary_duplicates(spark, d):
    return identity.boundary_duplicates(Layers(spark, d).table("documents"), "text", "source")


_BROKEN = "select case when feature_id % 97 = 0 then null else feature_id - (case when feature_id % 89 = 0 then feature_id % 7 else 0 end) end id, x0, y0, case when feature_id % 83 = 0 then x0 else x1 end x1, case when feature_id % 79 = 0 then null else y1 end y1 from crowd"


@workload("input_violations", sql(f"""select rule, id from (select unnest(list_filter([case when id is null then 'null_id' end, case when y1 is null then 'null_geometry' end, case when x1 <= x0 then 'degenerate_geometry' end, case when greatest(abs(x0), abs(y0), abs(x1), abs(y1)) > 20000 then 'out_of_range' end], lambda x: x is not null)) rule, id from ({_BROKEN}))
 union all select 'duplicate_id', id from ({_BROKEN}) where id is not null group by id having count(*) > 1"""))
def input_violations(spark, d):
    c, f = Layers(spark, d).crowd, F.col("feature_id")
    bad = c.select(F.when(f % 97 != 0, f - F.when(f % 89 == 0, f % 7).otherwise(0)).alias("id"), "x0", "y0", F.when(f % 83 == 0, F.col("x0")).otherwise(F.col("x1")).alias("x1"), F.when(f % 79 != 0, F.col("y1")).alias("y1"))
    return graph.validate_boxes(bad, "id", span=20_000)


def _closed(rings):
    return F.transform(rings, lambda r: F.concat(r, F.slice(r, F.lit(1), F.lit(1))))


@workload("ring_violations", sql("""select rule, entity_id id from (select entity_id, unnest(list_filter([case when entity_id % 31 = 0 then 'null_geometry' end, case when entity_id % 31 <> 0 and entity_id % 29 = 0 then 'unclosed_ring' end, case when entity_id % 31 <> 0 and entity_id % 29 <> 0 and entity_id % 23 = 0 then 'crossing_ring' end, case when entity_id % 19 = 0 then 'wrong_crs' end], lambda x: x is not null)) rule from entity)"""))
def ring_violations(spark, d):
    """Footprints with planted defects: no geometry, open rings, rings that cross themselves, another CRS."""
    k, rings = F.col("entity_id"), _closed(F.col("rings"))
    swap = lambda r: F.concat(F.slice(r, F.lit(1), F.lit(1)), F.slice(r, F.lit(3), F.lit(1)), F.slice(r, F.lit(2), F.lit(1)), F.slice(r, F.lit(4), F.size(r)))
    e = Layers(spark, d).entity_shapes
    # A bow tie's halves would cancel out in a square: its corner is moved, so that area stays.
    bow = F.array(swap(F.element_at(_closed(F.array(F.array(*[F.struct(x.cast("long").alias("x"), y.cast("long").alias("y")) for x, y in ((F.col("x0"), F.col("y0")), (F.col("x1"), F.col("y0")), (F.col("x1"), F.col("y1") + 50), (F.col("x0"), F.col("y1")))]))), 1)))
    bad = F.when(k % 31 == 0, F.lit(None)).when(k % 29 == 0, F.col("rings")).when(k % 23 == 0, bow).otherwise(rings)
    rows = e.select("entity_id", bad.alias("rings"), F.when(k % 19 == 0, "EPSG:4326").otherwise("EPSG:25832").alias("crs"))
    return graph.validate_rings(rows, "entity_id", crs="crs", expected="EPSG:25832")


@workload("facts_other_layers", sql("""select entity_id, city::bigint city, attr, source, trust::bigint trust, round(confidence, 9) confidence, v as value from (select entity_id, 'material' attr, 'pred' source, 1 trust, pixels / sum(pixels) over (partition by entity_id) confidence, cls v from predicted
 union all select entity_id, 'windows', 'recon', 3, 1.0, windows::varchar from recon union all select entity_id, 'doors', 'recon', 3, 1.0, doors::varchar from recon) join entity using (entity_id) where confidence >= 0.4"""))
def facts_other_layers(spark, d):
    """What the predicted and reconstructed layers say with a confidence of at least 0.4."""
    w = Layers(spark, d)
    out = provenance.layer_facts(w.entity, w.predicted, w.recon, min_conf=0.4)
    return out.select("entity_id", *long("city"), "attr", "source", *long("trust"), F.round("confidence", 9).alias("confidence"), "value")


@workload("graph_checks", sql("""select * from (values ('unique_ids', (select count(*) from entity) + (select count(*) from crowd) + (select count(*) from recon)), ('edge_ends', (select count(*) from edge)), ('spatial_coverage', (select count(*) from entity) + (select count(*) from crowd)), ('provenance_complete', (select count(*) from entity) + (select count(*) from crowd) + (select count(*) from recon) + (select count(*) from predicted))) t(name, expected) join (select true ok) on true join (select 1 one) on true""").replace("select * from (values", "select name, expected::bigint expected, expected::bigint actual, ok from (values"))
def graph_checks(spark, d):
    return graph.PropertyGraph.from_layers(Layers(spark, d)).checks().select("name", *long("expected", "actual"), "ok")


@workload("graph_invariants", "select unnest(['no_overwrite', 'external_identity', 'one_trust_class', 'edge_confidence']) as name, 0::bigint violations")
def graph_invariants(spark, d):
    return graph.PropertyGraph.from_layers(Layers(spark, d)).invariants()


# --- fusion -------------------------------------------------------------------------------------


@workload("fusion_candidates", sql("select city::bigint city, entity_id, feature_id, shared::bigint shared from cand"))
def fusion_candidates(spark, d):
    w = Layers(spark, d)
    return fusion.candidates(w.entity, w.crowd).select(*long("city"), "entity_id", "feature_id", *long("shared"))


@workload("fusion_edges", sql("select city::bigint city, entity_id, feature_id, shared::bigint shared, round(overlap, 9) overlap, round(jaccard, 9) jaccard from edge"))
def fusion_edges(spark, d):
    return _edges(Layers(spark, d)).select(*long("city"), "entity_id", "feature_id", *long("shared"), F.round("overlap", 9).alias("overlap"), F.round("jaccard", 9).alias("jaccard"))


def _joined(spark, d, strategy):
    w = Layers(spark, d)
    return fusion.candidates(w.entity, w.crowd, strategy=strategy).select("entity_id", "feature_id", *long("shared"))


for _s in ("grid", "levels", "nested"):
    workload("joint_index_overlap" if _s == "grid" else f"overlap_join_{_s}", sql("select entity_id, feature_id, shared::bigint shared from cand"))(lambda spark, d, s=_s: _joined(spark, d, s))


@workload("fusion_tau_sweep", sql("""select tau, count(*)::bigint edges, count(distinct entity_id)::bigint entities, count(distinct feature_id)::bigint features,
 count(*) filter (where fe = 1 and ef = 1)::bigint kind_11, count(*) filter (where fe > 1 and ef = 1)::bigint kind_1n, count(*) filter (where fe = 1 and ef > 1)::bigint kind_n1, count(*) filter (where fe > 1 and ef > 1)::bigint kind_nm
 from (select *, count(*) over (partition by tau, entity_id) fe, count(*) over (partition by tau, feature_id) ef from (select p / 10.0::double tau, entity_id, feature_id from cand, (select unnest(range(1, 10)) p) where 10 * shared >= p * least(area_a, area_b))) group by tau"""))
def fusion_tau_sweep(spark, d):
    w = Layers(spark, d)
    return fusion.sweep(fusion.candidates(w.entity, w.crowd), TAUS)


@workload("fusion_candidate_ratio", sql("select city::bigint city, count(*)::bigint candidates, count(*) filter (where 10 * shared >= 3 * least(area_a, area_b))::bigint accepted, round(count(*) / count(*) filter (where 10 * shared >= 3 * least(area_a, area_b)), 6) a_edge from cand group by grouping sets ((city), ())"))
def fusion_candidate_ratio(spark, d):
    """What the index costs: candidates for each accepted edge, per city and (city null) in all."""
    w = Layers(spark, d)
    rows = fusion.candidates(w.entity, w.crowd).select("city", fusion.accepted().cast("long").alias("ok"))
    out = rows.groupingSets([["city"], []], "city").agg(F.count(F.lit(1)).alias("candidates"), F.sum("ok").alias("accepted"))
    return out.select(*long("city"), "candidates", "accepted", F.round(F.col("candidates") / F.col("accepted"), 6).alias("a_edge"))


_COMPONENTS = """und as (select entity_id * 2 u, feature_id * 2 + 1 v from edge union select feature_id * 2 + 1, entity_id * 2 from edge),
reach(node, r) as (select u, u from und union select reach.node, und.v from reach join und on reach.r = und.u),
comp as (select node, min(r) component from reach group by node)"""


@workload("fusion_classes", sql("""select kind, count(*)::bigint components, sum(e)::bigint entities, sum(f)::bigint features, max(e + f)::bigint largest from (select e, f, case when e > 1 and f > 1 then 'n:m' when f > 1 then '1:n' when e > 1 then 'n:1' else '1:1' end kind
 from (select component, count(*) filter (where node % 2 = 0) e, count(*) filter (where node % 2 = 1) f from comp group by component)) group by kind""", _COMPONENTS))
def fusion_classes(spark, d):
    c = fusion.classify(fusion.components_of(_edges(Layers(spark, d))))
    return c.groupBy("kind").agg(F.count(F.lit(1)).alias("components"), F.sum("entities").alias("entities"), F.sum("features").alias("features"), F.max(F.col("entities") + F.col("features")).alias("largest"))


@workload("fusion_components_label", sql("select node, component from comp", _COMPONENTS))
def fusion_components_label(spark, d):
    return fusion.components_of(_edges(Layers(spark, d)), "label")


_DEGREE = """deg as (select *, count(*) over (partition by entity_id) fe, count(*) over (partition by feature_id) ef from edge)"""


@workload("fusion_degree_classes", sql("""select city::bigint city, case when ef > 1 and fe > 1 then 'n:m' when fe > 1 then '1:n' when ef > 1 then 'n:1' else '1:1' end kind, count(*)::bigint edges from deg group by 1, 2""", _DEGREE))
def fusion_degree_classes(spark, d):
    return fusion.degree_class(_edges(Layers(spark, d))).groupBy(F.col("city").cast("long").alias("city"), "kind").agg(F.count(F.lit(1)).alias("edges"))


_KINDS = """kinds as (select component, case when e > 1 and f > 1 then 'n:m' when f > 1 then '1:n' when e > 1 then 'n:1' else '1:1' end kind from (select component, count(*) filter (where node % 2 = 0) e, count(*) filter (where node % 2 = 1) f from comp group by component))"""


@workload("fusion_propagated", sql("""select entity_id, city::bigint city, crowd_height::bigint crowd_height, crowd_levels::bigint crowd_levels, crowd_status, sources::bigint sources, round(best_jaccard, 9) best_jaccard, kind, kind in ('n:1', 'n:m') shared_feature, kind = 'n:m' ambiguous from (
 select entity_id, city, max(case when r = 1 then crowd_height end) crowd_height, max(case when r = 1 then levels end) crowd_levels, string_agg(distinct status, ',' order by status) crowd_status, count(*) sources, max(jaccard) best_jaccard
 from (select edge.*, crowd_height, levels, status, row_number() over (partition by entity_id order by jaccard desc, edge.feature_id) r from edge join crowd using (feature_id)) group by 1, 2) join comp on node = entity_id * 2 join kinds using (component)""", _COMPONENTS, _KINDS))
def fusion_propagated(spark, d):
    w = Layers(spark, d)
    return fusion.propagate(_edges(w), w.crowd).select("entity_id", *long("city", "crowd_height", "crowd_levels"), "crowd_status", *long("sources"), F.round("best_jaccard", 9).alias("best_jaccard"), "kind", "shared_feature", "ambiguous")


def _part(a: str, b: str) -> str:
    """SQL for the area that two boxes share."""
    return f"(greatest(0, least({a}x1, {b}x1) - greatest({a}x0, {b}x0)) * greatest(0, least({a}y1, {b}y1) - greatest({a}y0, {b}y0)))"


_SHAPES = f"""es as (select city, entity_id, x0 ax0, y0 ay0, x1 ax1, y1 ay1, {", ".join(f"{v}0 + case entity_id % 3 when 0 then ({v}1 - {v}0) // 2 when 1 then ({v}1 - {v}0) // 4 else 0 end ac{v}0, case entity_id % 3 when 0 then {v}1 when 1 then {v}0 + ({v}1 - {v}0) // 4 + ({v}1 - {v}0) // 3 else {v}0 end ac{v}1" for v in "xy")} from entity),
cs as (select city, feature_id, x0 bx0, y0 by0, x1 bx1, y1 by1, {", ".join(f"{v}0 bc{v}0, {v}0 + case when feature_id % 2 = 0 then ({v}1 - {v}0) // 3 else 0 end bc{v}1" for v in "xy")} from crowd),
pcand as (select es.city, entity_id, feature_id, (ax1 - ax0) * (ay1 - ay0) - (acx1 - acx0) * (acy1 - acy0) area_a, (bx1 - bx0) * (by1 - by0) - (bcx1 - bcx0) * (bcy1 - bcy0) area_b,
 {_part("a", "b")} - {_part("ac", "b")} - {_part("a", "bc")} + {_part("ac", "bc")} shared from es join cs on es.city = cs.city and ax0 < bx1 and bx0 < ax1 and ay0 < by1 and by0 < ay1)"""


@workload("fusion_edges_polygon", sql("select city::bigint city, entity_id, feature_id, shared::double shared, round(shared::double / least(area_a, area_b), 9) overlap, round(shared::double / (area_a + area_b - shared), 9) jaccard from pcand where shared > 0 and 10 * shared >= 3 * least(area_a, area_b)", _SHAPES))
def fusion_edges_polygon(spark, d):
    """Fusion by footprints with corners cut out and holes: areas of the polygons, not of their boxes."""
    w = Layers(spark, d)
    out = fusion.edges(fusion.candidates(w.entity_shapes, w.crowd_shapes, geometry="polygon"))
    return out.select(*long("city"), "entity_id", "feature_id", F.col("shared").cast("double").alias("shared"), F.round("overlap", 9).alias("overlap"), F.round("jaccard", 9).alias("jaccard"))


@workload("footprint_centroids", sql("select entity_id, a::bigint area, round((bw * mx - cw * hx) / a, 6) x, round((bw * my - cw * hy) / a, 6) y from (select entity_id, (ax1 - ax0) * (ay1 - ay0)::double bw, (acx1 - acx0) * (acy1 - acy0)::double cw, bw - cw a, (ax0 + ax1) / 2.0 mx, (ay0 + ay1) / 2.0 my, (acx0 + acx1) / 2.0 hx, (acy0 + acy1) / 2.0 hy from es)", _SHAPES))
def footprint_centroids(spark, d):
    from provgraph.functions import geometry

    rows = Layers(spark, d).entity_shapes.select("entity_id", geometry.polygon_area(F.col("rings")).cast("long").alias("area"), geometry.polygon_centroid(F.col("rings")).alias("c"))
    return rows.select("entity_id", "area", F.round("c.x", 6).alias("x"), F.round("c.y", 6).alias("y"))


@workload("fusion_mutual_best", sql("""select entity_id, feature_id from (select *, row_number() over (partition by entity_id order by jaccard desc, feature_id) a, row_number() over (partition by feature_id order by jaccard desc, entity_id) b from edge) where a = 1 and b = 1"""))
def fusion_mutual_best(spark, d):
    return fusion.mutual_best(_edges(Layers(spark, d))).select("entity_id", "feature_id")


@workload("fusion_greedy")
def fusion_greedy(spark, d):
    return fusion.greedy_match(_edges(Layers(spark, d))).select("entity_id", "feature_id", "jaccard")


@workload("median_jaccard", sql("select city::bigint city, count(*)::bigint edges, round(quantile_cont(jaccard, 0.25), 9) q25, round(median(jaccard), 9) q50, round(quantile_cont(jaccard, 0.75), 9) q75 from edge group by grouping sets ((city), ())"))
def median_jaccard(spark, d):
    q = lambda p: F.round(F.percentile("jaccard", F.lit(p)), 9)
    return _edges(Layers(spark, d)).groupingSets([["city"], []], "city").agg(F.count(F.lit(1)).alias("edges"), q(0.25).alias("q25"), q(0.5).alias("q50"), q(0.75).alias("q75")).withColumn("city", F.col("city").cast("long"))


@workload("poi_inside", sql("select p.city::bigint city, poi_id, entity_id from poi p join entity e on p.city = e.city and x >= x0 and x < x1 and y >= y0 and y < y1"))
def poi_inside(spark, d):
    w = Layers(spark, d)
    return fusion.poi_inside(w.entity, w.poi).select(*long("city"), "poi_id", "entity_id")


_GRAMS = "select {id} id, len(g) size, unnest(g) item from (select {id}, list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) g from (select {id}, list_filter(regexp_split_to_array(lower(text), '\\s+'), lambda x: x <> '') w from {t}) where len(w) >= 5)"


@workload("doc_overlap_edges", f"""with a as ({_GRAMS.format(id='item_id', t='benchmark')}), b as ({_GRAMS.format(id='doc_id', t='documents')}), p as (select a.id item_id, b.id doc_id, a.size sa, b.size sb, count(*) k from a join b using (item) group by all)
 select item_id, doc_id, k::bigint shared, round(k / least(sa, sb), 9) overlap, round(k / (sa + sb - k), 9) jaccard from p where 10 * k >= 3 * least(sa, sb)""")
def doc_overlap_edges(spark, d):
    w = Layers(spark, d)
    pairs = fusion.set_overlap(fusion.shingles(w.table("benchmark"), "item_id", "text", 5), fusion.shingles(w.table("documents"), "doc_id", "text", 5))
    return pairs.where(fusion.accepted()).select(F.col("id_a").alias("item_id"), F.col("id_b").alias("doc_id"), *long("shared"), F.round("overlap", 9).alias("overlap"), F.round("jaccard", 9).alias("jaccard"))


# --- provenance, predictions, coverage -----------------------------------------------------------


@workload("pred_distribution", sql("select entity_id, cls, pixels from predicted"))
def pred_distribution(spark, d):
    w = Layers(spark, d)
    full = provenance.attach_distribution(w.entity.select("entity_id"), w.predicted)
    return full.select("entity_id", F.explode("pred_dist").alias("cls", "pixels"))


@workload("pred_dominant", sql("""select entity_id, cls, round(pixels / t, 6) share, round(h, 6) entropy, t::bigint pixels from (select *, sum(pixels) over (partition by entity_id) t, row_number() over (partition by entity_id order by pixels desc, cls) r from predicted)
 join (select entity_id, 0.0::double - sum(pixels / t * log2(pixels / t)) h from (select *, sum(pixels) over (partition by entity_id) t from predicted) group by 1) using (entity_id) where r = 1"""))
def pred_dominant(spark, d):
    return provenance.dominant(Layers(spark, d).predicted)


@workload("pred_coverage", sql("select city::bigint city, count(p)::bigint covered, count(*)::bigint total, round(count(p) / count(*), 6) coverage from (select city, entity_id, (select sum(pixels) from predicted x where x.entity_id = e.entity_id) p from entity e) group by 1"))
def pred_coverage(spark, d):
    w = Layers(spark, d)
    full = provenance.attach_distribution(w.entity.select("entity_id", "city"), w.predicted)
    return provenance.coverage_agg(full, ["city"], "pred_pixels", F.sum).select(*long("city", "covered", "total"), "coverage")


@workload("label_coverage", "select lang, source, avg(toxic) as value, count(toxic)::bigint covered, count(*)::bigint total, round(count(toxic) / count(*), 6) coverage, case when count(toxic) / count(*) >= 0.4 then 'ok' else 'insufficient' end status from documents left join labels using (doc_id) group by 1, 2".replace("avg(toxic) as value", "case when count(toxic) / count(*) >= 0.4 then round(avg(toxic), 9) end as value"))
def label_coverage(spark, d):
    w = Layers(spark, d)
    rows = w.table("documents").select("doc_id", "lang", "source").join(w.table("labels").select("doc_id", "toxic"), "doc_id", "left")
    return provenance.coverage_agg(rows, ["lang", "source"], "toxic", min_coverage=0.4).withColumn("value", F.round("value", 9))


@workload("recon_openings", sql("select entity_id, recon_id, windows, doors, windows + doors rings from recon"))
def recon_openings(spark, d):
    r = Layers(spark, d).recon
    nodes = provenance.openings(r).groupBy(F.col("entity_id").alias("_e")).agg(F.count(F.lit(1)).alias("rings"))
    return r.join(nodes, F.col("entity_id") == F.col("_e"), "left").select("entity_id", "recon_id", "windows", "doors", F.coalesce("rings", F.lit(0)).cast("long").alias("rings"))


_FACTS = """fact as (select entity_id, city, 'auth' source, 4 trust, 1.0::double confidence, auth_height::double v from entity where auth_height is not null union all select entity_id, edge.city, 'crowd', 2, jaccard, crowd_height::double from edge join crowd using (feature_id) where crowd_height is not null)"""


def _facts(spark, d, **options):
    w = Layers(spark, d)
    return provenance.height_facts(w.entity, _edges(w), w.crowd, **options)


def _shown(facts):
    return facts.select("entity_id", *long("city"), "source", *long("trust"), F.round("confidence", 9).alias("confidence"), "value")


@workload("trust_facts", sql("select trust::bigint trust, source, count(*)::bigint facts, count(distinct entity_id)::bigint entities from fact group by 1, 2", _FACTS))
def trust_facts(spark, d):
    return _facts(spark, d).groupBy(F.col("trust").cast("long").alias("trust"), "source").agg(F.count(F.lit(1)).alias("facts"), F.countDistinct("entity_id").alias("entities"))


@workload("facts_auth_only", sql("select entity_id, city::bigint city, source, trust::bigint trust, confidence, v as value from fact where trust >= 4", _FACTS))
def facts_auth_only(spark, d):
    return _shown(_facts(spark, d, min_trust=4))


@workload("facts_min_conf", sql("select entity_id, city::bigint city, source, trust::bigint trust, round(confidence, 9) confidence, v as value from fact where source = 'crowd' and confidence >= 0.5", _FACTS))
def facts_min_conf(spark, d):
    return _shown(_facts(spark, d, sources=["crowd"], min_conf=0.5))


@workload("value_authoritative_first", sql("select entity_id, city::bigint city, v as value, source from (select *, row_number() over (partition by entity_id order by trust desc, confidence desc, v desc) r from fact) where r = 1", _FACTS))
def value_authoritative_first(spark, d):
    return provenance.resolve_value(_facts(spark, d)).select("entity_id", *long("city"), "value", "source")


@workload("value_highest_confidence", sql("select entity_id, city::bigint city, v as value, source from (select *, row_number() over (partition by entity_id order by confidence desc, trust desc, v desc) r from fact) where r = 1", _FACTS))
def value_highest_confidence(spark, d):
    return provenance.resolve_value(_facts(spark, d), "highest_confidence").select("entity_id", *long("city"), "value", "source")


_AGREE = """ag as (select e.city, entity_id, feature_id, auth_height, crowd_height, case when auth_height is not null and crowd_height is not null then (case when abs(auth_height - crowd_height) <= 150 then 'agree' else 'disagree' end) when auth_height is not null then 'auth_only' when crowd_height is not null then 'crowd_only' else 'neither' end status
 from edge e join entity using (entity_id) join crowd using (feature_id))"""


def _agreed(spark, d):
    w = Layers(spark, d)
    rows = _edges(w).select("city", "entity_id", "feature_id").join(w.entity.select("entity_id", "auth_height"), "entity_id").join(w.crowd.select("feature_id", "crowd_height"), "feature_id")
    return rows.withColumn("status", provenance.agreement(F.col("auth_height"), F.col("crowd_height"), 150))


@workload("height_agreement", sql("select city::bigint city, status, count(*)::bigint edges from ag group by 1, 2", _AGREE))
def height_agreement(spark, d):
    return _agreed(spark, d).groupBy(F.col("city").cast("long").alias("city"), "status").agg(F.count(F.lit(1)).alias("edges"))


@workload("height_disagree_top", sql("select entity_id, feature_id, abs(auth_height - crowd_height)::bigint gap from ag where status = 'disagree' order by gap desc, entity_id, feature_id limit 20", _AGREE))
def height_disagree_top(spark, d):
    return _agreed(spark, d).where("status = 'disagree'").select("entity_id", "feature_id", F.abs(F.col("auth_height") - F.col("crowd_height")).cast("long").alias("gap")).orderBy(F.desc("gap"), "entity_id", "feature_id").limit(20)


@workload("height_crowd_only", sql("select city::bigint city, count(distinct entity_id)::bigint entities from ag where status = 'crowd_only' group by 1", _AGREE))
def height_crowd_only(spark, d):
    return _agreed(spark, d).where("status = 'crowd_only'").groupBy(F.col("city").cast("long").alias("city")).agg(F.countDistinct("entity_id").alias("entities"))


@workload("price_agreement", """select status, count(*)::bigint orders from (select case when l is null then 'no_lines' when abs(l - o_totalprice) <= 0.5 * o_totalprice then 'agree' else 'disagree' end status from orders left join (select l_orderkey, sum(l_extendedprice * (1 - l_discount) * (1 + l_tax)) l from lineitem group by 1) on l_orderkey = o_orderkey) group by 1""")
def price_agreement(spark, d):
    w = Layers(spark, d)
    net = w.table("lineitem").groupBy("l_orderkey").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))).alias("l"))
    rows = w.table("orders").select("o_orderkey", "o_totalprice").join(net, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    status = F.when(F.col("l").isNull(), "no_lines").when(F.abs(F.col("l") - F.col("o_totalprice")) <= 0.5 * F.col("o_totalprice"), "agree").otherwise("disagree")
    return rows.groupBy(status.alias("status")).agg(F.count(F.lit(1)).alias("orders"))


@workload("coverage_trap_citywide", sql("""select c.city::bigint city, cls, n::bigint n, covered::bigint covered, total::bigint total, round(covered / total, 6) coverage from (select city, count(*) total, count(p.entity_id) covered from entity left join (select distinct entity_id from predicted) p using (entity_id) group by 1) c
 left join (select city, cls, count(*) n from (select *, row_number() over (partition by entity_id order by pixels desc, cls) r from predicted) join entity using (entity_id) where r = 1 group by 1, 2) k on c.city = k.city"""))
def coverage_trap_citywide(spark, d):
    w = Layers(spark, d)
    best = provenance.dominant(w.predicted).select(F.col("entity_id").alias("_e"), "cls")
    rows = w.entity.select("city", "entity_id").join(best, F.col("entity_id") == F.col("_e"), "left")
    cover = provenance.coverage_agg(rows, ["city"], "cls", F.count)
    classes = rows.where("cls is not null").groupBy(F.col("city").alias("_c"), "cls").agg(F.count(F.lit(1)).alias("n"))
    return cover.join(classes, F.col("city") == F.col("_c"), "left").select(*long("city"), "cls", *long("n", "covered", "total"), "coverage")


@workload("event_coverage", """select status, count(*)::bigint customers from (select case when u is null then 'unavailable' when err then 'present' else 'known_false' end status from customer left join (select user_id u, bool_or(event_type = 'error') err from events group by 1) on u = c_custkey) group by 1""")
def event_coverage(spark, d):
    w = Layers(spark, d)
    seen = w.table("events").groupBy("user_id").agg(F.bool_or(F.col("event_type") == "error").alias("err"))
    rows = w.table("customer").select("c_custkey").join(seen, F.col("c_custkey") == F.col("user_id"), "left")
    return rows.groupBy(provenance.tri_state(F.col("user_id").isNotNull(), F.col("err")).alias("status")).agg(F.count(F.lit(1)).alias("customers"))


@workload("co_missing", sql("""select both_::bigint as "both", only_a::bigint only_a, only_b::bigint only_b, neither::bigint neither, round((both_::double * neither - only_a::double * only_b) / sqrt((both_ + only_a)::double * (only_b + neither) * (both_ + only_b) * (only_a + neither)), 6) phi from (
 select count(*) filter (where a and b) both_, count(*) filter (where a and not b) only_a, count(*) filter (where not a and b) only_b, count(*) filter (where not a and not b) neither from (select entity_id in (select entity_id from edge) a, entity_id in (select entity_id from predicted) b from entity where city = 3))"""))
def co_missing(spark, d):
    w = Layers(spark, d)
    a, b = (x.select(F.col("entity_id").alias(n)).distinct() for x, n in ((_edges(w), "_a"), (w.predicted, "_b")))
    rows = w.entity.where("city = 3").select("entity_id").join(a, F.col("entity_id") == F.col("_a"), "left").join(b, F.col("entity_id") == F.col("_b"), "left")
    return provenance.co_missing(rows, F.col("_a").isNotNull(), F.col("_b").isNotNull())


# --- space --------------------------------------------------------------------------------------

_GAP = "(greatest(b.x0 - a.x1, a.x0 - b.x1, 0) * greatest(b.x0 - a.x1, a.x0 - b.x1, 0) + greatest(b.y0 - a.y1, a.y0 - b.y1, 0) * greatest(b.y0 - a.y1, a.y0 - b.y1, 0))"


@workload("spatial_window", sql("select city::bigint city, count(*)::bigint n, sum(area)::bigint area from entity where x0 < 9000 and x1 > 2000 and y0 < 6000 and y1 > 1000 group by 1"))
def spatial_window(spark, d):
    return spatial.window(Layers(spark, d).entity, 2000, 1000, 9000, 6000).groupBy(F.col("city").cast("long").alias("city")).agg(F.count(F.lit(1)).alias("n"), F.sum("area").alias("area"))


_POIBOX = "(select poi_id, city, x x0, y y0, x x1, y y1 from poi)"


@workload("spatial_proximity", sql(f"select poi_id, entity_id, {_GAP}::bigint dist2 from {_POIBOX} a join entity b on a.city = b.city and {_GAP} <= 500 * 500"))
def spatial_proximity(spark, d):
    w = Layers(spark, d)
    return spatial.within(spatial.as_boxes(w.poi), w.entity.select("city", "entity_id", "x0", "y0", "x1", "y1"), 500).select("poi_id", "entity_id", *long("dist2"))


@workload("spatial_proximity_centres", sql("select e.city::bigint city, entity_id, poi_id, round(power((x0 + x1) / 2.0 - x, 2) + power((y0 + y1) / 2.0 - y, 2), 6) dist2 from entity e join poi p on e.city = p.city where power((x0 + x1) / 2.0 - x, 2) + power((y0 + y1) / 2.0 - y, 2) <= 90000"))
def spatial_proximity_centres(spark, d):
    """Points of interest at most 300 from an entity's centre."""
    w = Layers(spark, d)
    e = w.entity.select("city", "entity_id", "x0", "y0", "x1", "y1")
    out = spatial.within(e, spatial.as_boxes(w.poi), 300, metric="centre")
    return out.select(F.col("city_a").cast("long").alias("city"), "entity_id", "poi_id", F.round(F.col("dist2").cast("double"), 6).alias("dist2"))


@workload("spatial_knn", sql(f"select poi_id, entity_id, dist2::bigint dist2, r::bigint rank from (select poi_id, entity_id, {_GAP} dist2, row_number() over (partition by poi_id order by {_GAP}, entity_id) r from {_POIBOX} a join entity b on a.city = b.city) where r <= 3"))
def spatial_knn(spark, d):
    w = Layers(spark, d)
    return spatial.knn(spatial.as_boxes(w.poi), w.entity.select("city", "entity_id", "x0", "y0", "x1", "y1"), 3, a_id="poi_id", b_id="entity_id").select("poi_id", "entity_id", *long("dist2"), "rank")


@workload("spatial_multihop", sql(f"select distinct c.entity_id from entity c join edge using (entity_id) join crowd b using (feature_id) join {_POIBOX} a on a.city = b.city and {_GAP} <= 300 * 300"))
def spatial_multihop(spark, d):
    w = Layers(spark, d)
    near = spatial.within(spatial.as_boxes(w.poi), w.crowd.select("city", "feature_id", "x0", "y0", "x1", "y1"), 300).select(F.col("feature_id").alias("_f"))
    return _edges(w).join(near, F.col("feature_id") == F.col("_f"), "left_semi").select("entity_id").distinct()


@workload("spatial_3d", sql("select city::bigint city, tx, ty, sum(area * auth_height)::bigint volume, max(auth_height)::bigint tallest, max(storeys)::bigint storeys from entity where auth_height is not null group by 1, 2, 3"))
def spatial_3d(spark, d):
    e = Layers(spark, d).entity.where("auth_height is not null")
    return e.groupBy(F.col("city").cast("long").alias("city"), "tx", "ty").agg(F.sum(F.col("area") * F.col("auth_height")).alias("volume"), F.max("auth_height").alias("tallest"), F.max("storeys").alias("storeys"))


@workload("spatial_vertical_overlap", sql("""select entity_id, feature_id, greatest(0, least(eb + auth_height, fb + crowd_height) - greatest(eb, fb))::bigint shared_height, (greatest(0, least(eb + auth_height, fb + crowd_height) - greatest(eb, fb)) * shared)::bigint shared_volume from (select edge.*, auth_height, crowd_height, (entity_id * 13) % 500 eb, (feature_id * 17) % 500 fb from edge join entity using (entity_id) join crowd using (feature_id) where auth_height is not null and crowd_height is not null)"""))
def spatial_vertical_overlap(spark, d):
    """Matched objects as solids over their base elevation: the height, and the volume over the shared box, that they have in common."""
    w = Layers(spark, d)
    a = w.entity.where("auth_height is not null").select("entity_id", "auth_height", ((F.col("entity_id") * 13) % 500).alias("eb"))
    b = w.crowd.where("crowd_height is not null").select("feature_id", "crowd_height", ((F.col("feature_id") * 17) % 500).alias("fb"))
    rows = _edges(w).select("entity_id", "feature_id", "shared").join(a, "entity_id").join(b, "feature_id")
    rows = rows.withColumn("shared_height", spatial.vertical_overlap(F.col("eb"), F.col("auth_height"), F.col("fb"), F.col("crowd_height")))
    return rows.select("entity_id", "feature_id", *long("shared_height"), (F.col("shared_height") * F.col("shared")).cast("long").alias("shared_volume"))


@workload("spatial_density", sql("select city::bigint city, x0 // 3200 cx, y0 // 3200 cy, count(*)::bigint n, sum(area)::bigint built from entity group by 1, 2, 3"))
def spatial_density(spark, d):
    return spatial.density(Layers(spark, d).entity).withColumn("city", F.col("city").cast("long"))


# --- graph traversal and ordinary questions ------------------------------------------------------


@workload("hop_two", sql("select distinct a.entity_id entity_a, b.entity_id entity_b from edge a join edge b using (feature_id) where a.entity_id < b.entity_id"))
def hop_two(spark, d):
    g = graph.PropertyGraph.from_layers(Layers(spark, d)).tier(1)
    m = graph.Match(g).node("auth").edge("fusion").node("crowd").edge("fusion", out=False).node("auth").where(F.col("n0") < F.col("n2"))
    return m.rows.select(F.col("n0").alias("entity_a"), F.col("n2").alias("entity_b")).distinct()


@workload("hops_three", sql("select node, min(h)::int hop from walk group by node", """und as (select entity_id * 2 u, feature_id * 2 + 1 v from edge union select feature_id * 2 + 1, entity_id * 2 from edge),
walk(node, h) as (select entity_id * 2, 0 from entity where entity_id % 50 = 0 union select und.v, h + 1 from walk join und on node = u where h < 3)"""))
def hops_three(spark, d):
    w = Layers(spark, d)
    e = _edges(w).select((F.col("entity_id") * 2).alias("src"), (F.col("feature_id") * 2 + 1).alias("dst"))
    return graph.hops(e, w.entity.where("entity_id % 50 = 0").select((F.col("entity_id") * 2).alias("node")), 3)


@workload("canonical_evidence", sql("select e.entity_id, e.city::bigint city, count(feature_id)::bigint crowd_links, coalesce(any_value(n), 0)::bigint pred_classes from entity e left join edge using (entity_id) left join (select entity_id, count(*) n from predicted group by 1) using (entity_id) group by 1, 2"))
def canonical_evidence(spark, d):
    w = Layers(spark, d)
    links = _edges(w).groupBy(F.col("entity_id").alias("_a")).agg(F.collect_list(F.struct("feature_id", "jaccard")).alias("crowd"))
    pred = w.predicted.groupBy(F.col("entity_id").alias("_b")).agg(F.collect_list(F.struct("cls", "pixels")).alias("pred"))
    rows = w.entity.select("entity_id", "city").join(links, F.col("entity_id") == F.col("_a"), "left").join(pred, F.col("entity_id") == F.col("_b"), "left")
    n = lambda c: F.when(F.col(c).isNull(), 0).otherwise(F.size(c)).cast("long")
    return rows.select("entity_id", *long("city"), n("crowd").alias("crowd_links"), n("pred").alias("pred_classes"))


@workload("lookup_entity", sql('select entity_id, city::bigint city, district::bigint district, storeys::bigint storeys, "function" from entity where entity_id = 42'))
def lookup_entity(spark, d):
    return Layers(spark, d).entity.where("entity_id = 42").select("entity_id", *long("city", "district", "storeys"), "function")


@workload("filter_entities", sql("select entity_id, storeys::bigint storeys from entity where \"function\" = 'BUILDING' and storeys >= 6"))
def filter_entities(spark, d):
    return Layers(spark, d).entity.where("function = 'BUILDING' and storeys >= 6").select("entity_id", *long("storeys"))


@workload("agg_by_function", sql('select city::bigint city, "function", count(*)::bigint n, round(avg(storeys), 6) avg_storeys from entity group by 1, 2'))
def agg_by_function(spark, d):
    return Layers(spark, d).entity.groupBy(F.col("city").cast("long").alias("city"), "function").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("storeys"), 6).alias("avg_storeys"))


for _key, _city in (("floor_area", 4), ("volume", 4), ("year_built", 4), ("vintage", 0)):

    def _thematic(spark, d, key=_key, city=_city):
        e = Layers(spark, d).entity.where(F.col("city") == city)
        return provenance.coverage_agg(e, ["district"], key, F.sum).select(*long("district", "value", "covered", "total"), "coverage")

    workload(f"thematic_{_key}", sql(f"select district::bigint district, sum({_key})::bigint as value, count({_key})::bigint covered, count(*)::bigint total, round(count({_key}) / count(*), 6) coverage from entity where city = {_city} group by 1"))(_thematic)


@workload("thematic_native_keys", sql('select "用途", count(*)::bigint n, count("構造")::bigint "構造" from entity where city = 2 group by 1'))
def thematic_native_keys(spark, d):
    return Layers(spark, d).entity.where("city = 2").groupBy("`用途`").agg(F.count(F.lit(1)).alias("n"), F.count("`構造`").alias("構造"))


@workload("doc_near_copies", f"""with g as ({_GRAMS.format(id='doc_id', t='documents')}), sig as (select id, size, md5(string_agg(item, '|' order by item)) h from g group by 1, 2), rep as (select min(id) id from sig group by h),
 r as (select g.* from g join rep using (id)), p as (select a.id id_a, b.id id_b, a.size sa, b.size sb, count(*) k from r a join r b on a.item = b.item and a.id < b.id group by all)
 select id_a, id_b, k::bigint shared, round(k / (sa + sb - k), 9) jaccard from p where 100 * k >= 80 * (sa + sb - k)""")
def doc_near_copies(spark, d):
    """The set twin on near copies, by bands of minimum hashes."""
    return fusion.near_sets(Layers(spark, d).table("documents"), "doc_id", "text").withColumn("jaccard", F.round("jaccard", 9))


@workload("index_layers", sql("""select layer, sum(((x1 - 1) // 800 - x0 // 800 + 1) * ((y1 - 1) // 800 - y0 // 800 + 1))::bigint cells from (select 'auth' layer, x0, y0, x1, y1 from entity union all select 'crowd', x0 + 8000, y0 + 8000, x1 + 8000, y1 + 8000 from crowd) group by 1"""))
def index_layers(spark, d):
    """Each source has an index layer of its own; both can be read alone or together."""
    w, box = Layers(spark, d), ["x0", "y0", "x1", "y1"]
    both = spatial.index(w.entity.select(*box), layer="auth").union(spatial.index(w.crowd.select(*box), layer="crowd"))
    return both.groupBy("layer").agg(F.count(F.lit(1)).alias("cells"))


@workload("availability_tier1", sql("select city::bigint city, sum(a)::bigint auth, sum(c)::bigint crowd from (select city, 1 a, 0 c from entity union all select city, 0, 1 from crowd) group by 1"))
def availability_tier1(spark, d):
    return graph.PropertyGraph.from_layers(Layers(spark, d)).tier(1).availability().select(*long("city", "auth", "crowd"))


@workload("value_authoritative_only", sql("select entity_id, city::bigint city, v as value, source from fact where source = 'auth'", _FACTS))
def value_authoritative_only(spark, d):
    return provenance.resolve_value(_facts(spark, d), "authoritative_only").select("entity_id", *long("city"), "value", "source")
