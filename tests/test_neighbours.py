"""Questions on nearness at size: joins on cells give what all pairs give."""
import re

import pytest
from pyspark.sql import functions as F

from provgraph.questions import neighbours, suite
from provgraph.questions.templates import ALL, GAP

KEYED = [t for t in ALL if neighbours.indexed(t.gold.replace(" C", " 3").replace(" S)", " 7)")) != t.gold.replace(" C", " 3").replace(" S)", " 7)")]


@pytest.fixture(scope="module")
def asked(spark, sf):
    s = suite.Suite(spark, sf)
    return s, s.questions()


def _plain(s, text):
    return s.spark.sql(re.sub(rf"\b(from|join)\s+({'|'.join(suite.VIEWS)})\b", rf"\1 {s.prefix}\2", text))


def test_all_nearness_templates_are_keyed():
    assert {t.number for t in KEYED} == {t.number for t in ALL if f"{GAP} <=" in t.gold or "abs(e.tx" in t.gold} and len(KEYED) >= 6


@pytest.mark.parametrize("city", [1, 3])
def test_same_answers_without_all_pairs(asked, city):
    s, q = asked
    for x in q:
        if x["city"] == city and x["lang"] == "en" and x["template"] in {t.number for t in KEYED}:
            keyed = s.spark.sql(s.sql(x["gold"]))
            plan = keyed._jdf.queryExecution().optimizedPlan().toString()
            assert "_cx" in plan or "_nx" in plan, x["gold"]
            assert tuple(suite.canonical(keyed).first()) == tuple(suite.canonical(_plain(s, x["gold"])).first()), x["gold"]


@pytest.mark.parametrize("d2", [0, 1, 2, 3600, 640_000, 641_601, 4_000_000])
def test_bounds_on_cell_borders(spark, d2):
    """Boxes on both sides of cells' borders and of zero, some of them points, at squared distances that aren't squares too."""
    at = [-1601, -800, -1, 0, 1, 799, 800, 801, 1600, 2401]
    rows = [(i * 100 + j * 10 + k, 1, x, y, x + w, y + w) for i, x in enumerate(at) for j, y in enumerate(at) for k, w in enumerate((0, 1, 900))]
    spark.createDataFrame(rows, "feature_id long, city int, x0 long, y0 long, x1 long, y1 long").createOrReplaceTempView("crowd")
    text = f"select count(*), sum(a.feature_id * 7 + b.feature_id) from crowd a join crowd b on a.city = b.city and a.city = 1 and {GAP} <= {d2}"
    assert neighbours.indexed(text) != text and spark.sql(neighbours.indexed(text)).first() == spark.sql(text).first()
    spark.catalog.dropTempView("crowd")


def test_unnamed_columns_stay():
    text = f"select * from entity a join entity b on a.city = b.city and a.city = 1 and {GAP} <= 9"
    assert neighbours.indexed(text) == text and neighbours.indexed(text.replace("*", "a.*", 1)) == text.replace("*", "a.*", 1)
    assert neighbours.indexed("select frm x") == "select frm x"
    named = text.replace("*", "a.entity_id", 1)
    assert neighbours.indexed(named) != named == neighbours.indexed(named, boxes=False)
    for other in (named + " or true", named + " * 4", named.replace("from entity a", "from (select 1 x0) a")):
        assert neighbours.indexed(other) == other


def test_boxes_without_coordinates_are_near_to_all(spark, sf, tmp_path):
    """A customer without a key has no box; the measure takes it for near, so nothing is keyed then."""
    for t in ("nation", "orders", "lineitem", "events", "pages", "supplier", "part"):
        spark.read.parquet(f"{sf}/{t}.parquet").write.parquet(f"{tmp_path}/{t}.parquet")
    c = spark.read.parquet(f"{sf}/customer.parquet")
    c.union(c.limit(1).withColumn("c_custkey", F.lit(None).cast("long"))).write.parquet(f"{tmp_path}/customer.parquet")
    s = suite.Suite(spark, str(tmp_path))
    text = f"select count(*) from entity a join entity b on a.city = b.city and {GAP} <= 3600"
    assert not s.boxes and s.spark.sql(s.sql(text)).first() == _plain(s, text.replace("entity a", "entity as a").replace("entity b", "entity as b")).first()
