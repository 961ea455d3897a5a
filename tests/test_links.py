"""Link tables at size: kinds without components, random negatives without nearest features."""
import numpy as np

from provgraph.operators import fusion, spatial
from provgraph.plans import learning
from provgraph.sources.overlay import Layers


def test_kinds_equal_those_of_the_components(spark):
    """Chains, stars on both sides, single links, a repeated one and null ends."""
    r = np.random.default_rng(3)
    rows = [(1, 1), (1, 1), (2, 2), (2, 3), (3, 4), (4, 4), (5, 5), (5, 6), (6, 6), (7, 7), (7, 8), (8, 8), (8, 9), (9, 9), (None, 1), (2, None)]
    rows += [(int(a) + 100, int(b) + 100) for a, b in r.integers(0, 60, (50, 2))]
    edge = spark.createDataFrame(rows, "entity_id long, feature_id long")
    got, want = (sorted(map(tuple, f(edge).where("entity_id is not null and feature_id is not null").select("entity_id", "feature_id", "kind").collect())) for f in (fusion.edge_kinds, fusion.edge_classes))
    assert got == want and {k for _, _, k in got} == {"1:1", "1:n", "n:1", "n:m"}


def test_random_negatives_need_no_search(spark, sf, monkeypatch):
    """No search for nearest features and no components; every positive is a hidden edge, every negative no hidden one."""

    def refuse(*a, **k):
        raise AssertionError("not needed")

    monkeypatch.setattr(spatial, "knn", refuse)
    monkeypatch.setattr(fusion, "components_of", refuse)
    w = Layers(spark, sf)
    pairs = learning.link_ego(w, "random").selectExpr("entity_id", "inline(pairs)").collect()
    monkeypatch.undo()
    hidden = {(r[0], r[1]): r[2] for r in fusion.edge_classes(learning._edges(w)).where("(entity_id * 31 + feature_id * 17) % 3 = 0").select("entity_id", "feature_id", "kind").collect()}
    assert {(r["entity_id"], r["feature_id"]): r["kind"] for r in pairs if r["label"] == 1} == hidden
    assert not hidden.keys() & {(r["entity_id"], r["feature_id"]) for r in pairs if r["label"] == 0} and any(r["label"] == 0 for r in pairs)
