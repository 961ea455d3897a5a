"""84 question templates over the graph's views, with what each needs and its gold query.

C stands for the city, S for a slot value read from the graph.  A template is asked in every city: where
its tokens exist it is feasible (coverage-aware if the tokens cover only part), elsewhere it is
infeasible and a guard query proves that the tokens are absent.
"""
from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class Template:
    number: int
    category: str
    kind: str
    text: str
    gold: str
    needs: tuple[str, ...] = ()
    slot: str = ""
    ordered: bool = False
    may_be_empty: bool = True
    others: dict = field(default_factory=dict)  # texts in further languages


def _box(n: int) -> str:
    return f"x0 < {9000 + n} and x1 > 2000 and y0 < 6000 and y1 > 1000"


#: The squared distance between boxes a and b.
GAP = "pow(greatest(b.x0 - a.x1, a.x0 - b.x1, 0), 2) + pow(greatest(b.y0 - a.y1, a.y0 - b.y1, 0), 2)"
#: Points of interest as boxes.
POINTS = "(select poi_id, city, x x0, y y0, x x1, y y1 from poi)"
_NEAR = "from {a} a join {b} b on a.city = b.city and a.city = C and " + GAP
_DEG = "(select entity_id, count(*) n from fusion_edge where city = C group by 1)"
_AGREE = "fusion_edge join entity using (entity_id, city) join crowd using (feature_id, city) where city = C"


def _templates() -> list[tuple]:
    s, x, p, c, t = "spatial", "cross_source", "provenance", "coverage", "thematic"
    near = lambda a, b, d, out: f"select {out} {_NEAR.format(a=a, b=b)} <= {d * d}"
    return [
        (s, "window", "How many buildings are in the box?", f"select count(*) from entity where city = C and {_box(0)}", ()),
        (s, "window", "List the buildings in the box.", f"select entity_id from entity where city = C and {_box(500)}", ()),
        (s, "window", "What is the built area in the box?", f"select sum(area) from entity where city = C and {_box(900)}", ()),
        (s, "proximity", "How many buildings are within 500 of building S?", near("(select * from entity where entity_id = S)", "entity", 500, "count(*)"), (), "entity_id"),
        (s, "proximity", "Which buildings are within 400 of a point of interest?", near(POINTS, "entity", 400, "distinct b.entity_id"), ()),
        (s, "proximity", "How many pairs of buildings are within 60?", near("entity", "entity", 60, "count(*)") + " and a.entity_id < b.entity_id", ()),
        (s, "nearest", "Which point of interest is nearest to building S?", f"select b.poi_id from (select * from entity where entity_id = S) a join {POINTS} b on a.city = b.city order by {GAP}, b.poi_id limit 1", (), "entity_id"),
        (s, "nearest", "Which three buildings are nearest to building S?", f"select b.entity_id from (select * from entity where entity_id = S) a join entity b on a.city = b.city and a.entity_id <> b.entity_id order by {GAP}, b.entity_id limit 3", (), "entity_id"),
        (s, "nearest", "Which crowd feature is nearest to building S without being linked?", f"select b.feature_id from (select * from entity where entity_id = S) a join crowd b on a.city = b.city where b.feature_id not in (select feature_id from fusion_edge where entity_id = S) order by {GAP}, b.feature_id limit 1", (), "entity_id"),
        (s, "multi_hop", "Which buildings are linked to a crowd feature within 300 of a point of interest?", f"select distinct entity_id from fusion_edge where feature_id in (select b.feature_id {_NEAR.format(a=POINTS, b='crowd')} <= 90000)", ()),
        (s, "multi_hop", "How many tiles touch a tile of five or more buildings?", "select count(distinct e.tx * 100 + e.ty) from entity e join (select tx, ty from entity where city = C group by 1, 2 having count(*) >= 5) d on abs(e.tx - d.tx) + abs(e.ty - d.ty) = 1 where e.city = C", ()),
        (s, "multi_hop", "How many households are within 200 of a factory?", near("(select * from entity where function = 'MACHINERY')", "(select * from entity where function = 'HOUSEHOLD')", 200, "count(distinct b.entity_id)"), ()),
        (s, "solid", "What is the volume of building stock by district?", "select district, sum(area * auth_height) from entity where city = C group by 1", ("auth_height",)),
        (s, "solid", "How tall is the tallest building of each tile?", "select tx, ty, max(auth_height) from entity where city = C group by 1, 2", ("auth_height",)),
        (s, "solid", "How many buildings have each number of storeys?", "select storeys, count(*) from entity where city = C group by 1", ()),
        (s, "density", "How many buildings are in each tile?", "select tx, ty, count(*) from entity where city = C group by 1, 2", ()),
        (s, "density", "What is the built area of each tile?", "select tx, ty, sum(area) from entity where city = C group by 1, 2", ()),
        (s, "density", "Which five tiles have most buildings?", "select tx, ty, count(*) n from entity where city = C group by 1, 2 order by n desc, tx, ty limit 5", ()),
        (s, "joint", "What area do both layers share?", "select sum(shared) from fusion_edge where city = C", ()),
        (s, "joint", "How many crowd features overlap no building?", "select count(*) from crowd where city = C and feature_id not in (select feature_id from fusion_edge)", ()),
        (x, "compare", "On how many links do both heights agree?", f"select count(*) from {_AGREE} and abs(auth_height - crowd_height) <= 150", ("auth_height",)),
        (x, "compare", "On which links do the heights disagree?", f"select entity_id, feature_id from {_AGREE} and abs(auth_height - crowd_height) > 150", ("auth_height",)),
        (x, "compare", "By how much does the crowd overstate heights in each tile?", f"select tx, ty, round(avg(crowd_height - auth_height), 3) from {_AGREE} group by 1, 2", ("auth_height",)),
        (x, "compare", "On how many links do levels and storeys differ?", f"select count(*) from {_AGREE} and levels <> storeys", ()),
        (x, "fill_in", "What crowd heights are there where no surveyed one is?", f"select entity_id, crowd_height from {_AGREE} and auth_height is null and crowd_height is not null", ()),
        (x, "fill_in", "How many buildings have only a crowd height?", f"select count(distinct entity_id) from {_AGREE} and auth_height is null and crowd_height is not null", ()),
        (x, "fill_in", "What is the mean crowd height where no surveyed one is?", f"select round(avg(crowd_height), 3) from {_AGREE} and auth_height is null", ()),
        (x, "classes", "How do predicted classes spread over surveyed roof types?", "select roof, cls, count(*) from entity join predicted using (entity_id, city) where city = C group by 1, 2", ("predicted", "roof")),
        (x, "classes", "How do predicted classes spread over crowd states?", "select cls, status, count(*) from predicted join fusion_edge using (entity_id, city) join crowd using (feature_id, city) where city = C group by 1, 2", ("predicted",)),
        (x, "degree", "How many buildings have three or more crowd features?", f"select count(*) from {_DEG} where n >= 3", ()),
        (x, "degree", "How many crowd features lie on two or more buildings?", "select count(*) from (select feature_id from fusion_edge where city = C group by 1 having count(*) >= 2)", ()),
        (x, "degree", "How are buildings spread over numbers of links?", f"select n, count(*) from {_DEG} group by 1", ()),
        (x, "degree", "What is the largest number of links of one building?", f"select max(n) from {_DEG}", ()),
        (x, "degree", "What share of links is ambiguous on both sides?", "select round(avg(case when fe > 1 and ef > 1 then 1.0 else 0.0 end), 6) from (select count(*) over (partition by entity_id) fe, count(*) over (partition by feature_id) ef from fusion_edge where city = C)", ()),
        (p, "by_source", "What is the mean height, by authoritative data only?", "select round(avg(value), 3) from fact where city = C and source = 'auth'", ("auth_height",)),
        (p, "by_source", "How many heights are authoritative?", "select count(*) from fact where city = C and source = 'auth'", ("auth_height",)),
        (p, "by_source", "What is the greatest height, by authoritative data only?", "select max(value) from fact where city = C and source = 'auth'", ("auth_height",)),
        (p, "by_confidence", "Which links have a confidence of 0.5 or more?", "select entity_id, feature_id from fusion_edge where city = C and jaccard >= 0.5", ()),
        (p, "by_confidence", "How many links have a confidence of 0.7 or more?", "select count(*) from fusion_edge where city = C and jaccard >= 0.7", ()),
        (p, "by_confidence", "Which buildings have a link of 0.6 or more?", "select distinct entity_id from fusion_edge where city = C and jaccard >= 0.6", ()),
        (p, "evidence", "What is the most confident height of building S?", "select max_by(value, struct(confidence, trust, value)) from fact where entity_id = S", (), "entity_id"),
        (p, "evidence", "What evidence is there on the height of building S?", "select source, value from fact where entity_id = S", (), "entity_id"),
        (p, "trust", "How many facts does each trust class hold?", "select trust, count(*) from fact where city = C group by 1", ()),
        (p, "trust", "How many buildings have derived evidence only?", "select count(*) from (select entity_id from fact where city = C group by 1 having max(trust) < 4)", ()),
        (p, "reconstructed", "How many openings of each kind were reconstructed?", "select sum(windows), sum(doors) from recon where city = C", ("recon",)),
        (p, "reconstructed", "Which buildings have a reconstructed facade?", "select entity_id from recon where city = C", ("recon",)),
        (c, "count", "How many buildings of each material are there, and how many are covered?", "select cls, count(*), (select count(distinct entity_id) from predicted where city = C), (select count(*) from entity where city = C) from predicted where city = C group by 1", ("predicted",)),
        (c, "share", "What share of covered buildings has class LARGE?", "select round(count(distinct case when cls = 'LARGE' then entity_id end) / count(distinct entity_id), 6), count(distinct entity_id) from predicted where city = C", ("predicted",)),
        (c, "mean", "What is the mean height, and of how many buildings is it known?", "select round(avg(auth_height), 3), count(auth_height), count(*) from entity where city = C", ("auth_height",)),
        (c, "mean", "What is the mean height of tiles with at least 90 percent known?", "select tx, ty, round(avg(auth_height), 3) from entity where city = C group by 1, 2 having count(auth_height) / count(*) >= 0.9", ("auth_height",)),
        (c, "share", "What share of buildings has a crowd match?", "select round(count(distinct f.entity_id) / count(distinct e.entity_id), 6), count(distinct e.entity_id) from entity e left join fusion_edge f on e.entity_id = f.entity_id where e.city = C", ()),
        (c, "share", "What share of crowd features has no match?", "select round(1 - count(distinct f.feature_id) / count(distinct b.feature_id), 6), count(distinct b.feature_id) from crowd b left join fusion_edge f on b.feature_id = f.feature_id where b.city = C", ()),
        (c, "share", "What share of owners was ever active?", "select round(avg(case when a.user_id is null then 0.0 else 1.0 end), 6), count(*) from entity left join (select distinct user_id from activity) a on user_id = entity_id where city = C", ()),
        (c, "mean", "What is the mean activity of the owners that were active?", "select round(avg(v), 6), count(v), count(*) from entity left join (select user_id, sum(value) v from activity group by 1) on user_id = entity_id where city = C", ()),
        (c, "unknown", "Of how many buildings is the material unknown?", "select count(*) - count(p.entity_id), count(*) from entity e left join (select distinct entity_id from predicted) p on e.entity_id = p.entity_id where city = C", ("predicted",)),
        (c, "unknown", "How many buildings lack both material and crowd match?", "select count(*) from entity where city = C and entity_id not in (select entity_id from predicted) and entity_id not in (select entity_id from fusion_edge)", ("predicted",)),
        ("infeasible", "attribute", "Who owns each building by name?", "select entity_id, owner_name from entity where city = C", ("owner_name",)),
        ("infeasible", "attribute", "What energy class has each building?", "select entity_id, energy_class from entity where city = C", ("energy_class",)),
        ("infeasible", "attribute", "How many people live in each building?", "select entity_id, population from entity where city = C", ("population",)),
        ("infeasible", "attribute", "What rent is paid in each building?", "select entity_id, rent from entity where city = C", ("rent",)),
        ("infeasible", "layer", "Which material is most common?", "select cls from predicted where city = C group by 1 order by count(*) desc, cls limit 1", ("predicted",)),
        ("infeasible", "layer", "How many windows do the facades have?", "select sum(windows) from recon where city = C", ("recon",)),
        ("infeasible", "elsewhere", "What is the total floor area?", "select sum(floor_area) from entity where city = C", ("floor_area",)),
        ("infeasible", "elsewhere", "How old is the data?", "select min(vintage) from entity where city = C", ("vintage",)),
        ("lookup", "record", "What are the storeys and function of building S?", "select storeys, function from entity where entity_id = S", (), "entity_id"),
        ("lookup", "record", "What function has building S?", "select function from entity where entity_id = S", (), "entity_id"),
        ("lookup", "record", "In which district is building S?", "select district from entity where entity_id = S", (), "entity_id"),
        ("filter", "condition", "Which buildings are households?", "select entity_id from entity where city = C and function = 'HOUSEHOLD'", ()),
        ("filter", "condition", "Which buildings have eight or more storeys?", "select entity_id from entity where city = C and storeys >= 8", ()),
        ("filter", "condition", "Which buildings are between 1000 and 2000 tall?", "select entity_id from entity where city = C and auth_height between 1000 and 2000", ("auth_height",)),
        ("aggregate", "group", "How many buildings has each function?", "select function, count(*) from entity where city = C group by 1", ()),
        ("aggregate", "group", "How many storeys has each district on average?", "select district, round(avg(storeys), 4) from entity where city = C group by 1", ()),
        ("aggregate", "group", "What is the median number of storeys?", "select percentile(storeys, 0.5) from entity where city = C", ()),
        ("multi_hop", "path", "Which states do the features linked to building S have?", "select status, count(*) from fusion_edge join crowd using (feature_id, city) where entity_id = S group by 1", (), "entity_id"),
        ("multi_hop", "path", "How many features are linked in each district?", "select district, count(distinct feature_id) from entity join fusion_edge using (entity_id, city) where city = C group by 1", ()),
        ("multi_hop", "path", "How many pairs of buildings share a feature?", "select count(distinct a.entity_id, b.entity_id) from fusion_edge a join fusion_edge b on a.feature_id = b.feature_id and a.entity_id < b.entity_id where a.city = C", ()),
        (t, "area", "What is the floor area by district?", "select district, sum(floor_area), count(floor_area), count(*) from entity where city = C group by 1", ("floor_area",)),
        (t, "volume", "What is the volume for each number of storeys?", "select storeys, sum(volume) from entity where city = C group by 1", ("volume",)),
        (t, "year", "How many buildings were built before 1950?", "select count(*) from entity where city = C and year_built < 1950", ("year_built",)),
        (t, "vintage", "How many buildings has each data vintage?", "select vintage, count(*) from entity where city = C group by 1", ("vintage",)),
        (t, "vintage", "What is the newest data of each district?", "select district, max(vintage) from entity where city = C group by 1", ("vintage",)),
        (t, "native_key", "Which buildings are dwellings?", "select entity_id from entity where city = C and `用途` = '住宅'", ("用途",)),
        (t, "native_key", "How many buildings have each use?", "select `用途`, count(*) from entity where city = C group by 1", ("用途",)),
        (t, "native_key", "Which structures are recorded?", "select distinct `構造` from entity where city = C and `構造` is not null", ("構造",)),
    ]


_OTHER = {
    1: ("Wie viele Gebäude liegen im Rechteck?", "範囲内の建物はいくつですか。"),
    7: ("Welcher Ort von Interesse liegt Gebäude S am nächsten?", "建物Sに最も近い施設はどれですか。"),
    16: ("Wie viele Gebäude hat jede Kachel?", "各タイルの建物はいくつですか。"),
    21: ("Bei wie vielen Verbindungen stimmen beide Höhen überein?", "両方の高さが一致する対応はいくつですか。"),
    35: ("Wie hoch sind Gebäude im Mittel, nur nach amtlichen Daten?", "公的データのみでの平均の高さはいくらですか。"),
    47: ("Wie viele Gebäude je Material gibt es, und wie viele sind erfasst?", "材料ごとの建物数と対象数はいくつですか。"),
    71: ("Wie viele Gebäude hat jede Funktion?", "用途別の建物数はいくつですか。"),
    82: ("Welche Gebäude sind Wohnhäuser?", "住宅である建物はどれですか。"),
    83: ("Wie viele Gebäude hat jede Nutzung?", "用途ごとの建物はいくつですか。"),
    84: ("Welche Bauweisen sind verzeichnet?", "記録されている構造は何ですか。"),
}
ALL = [Template(i, *r[:4], tuple(r[4]), r[5] if len(r) > 5 else "", " order by " in r[3], True, dict(zip(("de", "ja"), _OTHER.get(i, ())))) for i, r in enumerate(_templates(), 1)]
