"""What the third round's findings showed: pairs that were left out, encoders and scorers that were left out, training in one pass."""
import dataclasses
import pickle

import duckdb
import numpy as np
import pytest

from provgraph import workloads
from provgraph.learn import encoders, features, tape, train
from provgraph.plans import learning
from provgraph.sources.overlay import Layers


def same(spark, folder, name, **tables):
    """The query on ``tables``, and its SQL's rows on the same."""
    c = duckdb.connect()
    for t, df in tables.items():
        df.coalesce(1).write.parquet(f"{folder}/{t}.parquet")
        c.execute(f"create view {t} as select * from '{folder}/{t}.parquet/*.parquet'")
    want = c.sql(workloads.oracle_sql()[name])
    got = [tuple(r) for r in workloads.queries()[name](spark, str(folder)).select(*want.columns).collect()]
    return sorted(got, key=str), sorted(want.fetchall(), key=str)


def test_hub_join_has_all_pairs(spark, tmp_path):
    """Keys of any distance pair up; equal, negative and missing balances, a hub of one, missing hubs."""
    hubs = [(1, "A"), (1, "B"), (2, "A")]
    rows = [(i * 7, *hubs[i % 3], None if i % 11 == 0 else round(((i * 7919) % 2003 - 900) * 1.25, 2)) for i in range(200)]
    rows += [(9001, 3, "A", 5.0), (9002, None, "A", 5.0), (9003, None, "A", 6.0), (9004, 4, "C", None), (9005, 4, "C", None), (9006, 4, "D", None), (9007, 4, "D", 2.0), (9008, 1, None, 3.0), (9009, 5, "E", 4.5), (9010, 5, "E", 4.5)]
    got, want = same(spark, tmp_path, "op_join_self_hub", customer=spark.createDataFrame(rows, "c_custkey long, c_nationkey int, c_mktsegment string, c_acctbal double"))
    assert got == want and (1, "A", 67 * 66 // 2) in {r[:3] for r in got} and (5, "E", 1, 0.0) in got and (4, "C", 1, None) in got


def test_names_of_other_sizes_are_compared(spark, tmp_path):
    """Parts of one brand pair up whatever their sizes; every two of them get the distance of their names through their classes."""
    rows = [(i, f"Brand#{i % 2}", None if i == 5 else i % 4, f"part{'x' * (i % 7)}{i % 3}") for i in range(40)]
    got, want = same(spark, tmp_path, "op_str_similarity", part=spark.createDataFrame(rows, "p_partkey long, p_brand string, p_size int, p_name string"))
    assert got == want
    rep = {b: a for kind, a, b, _ in got if kind == "member"}
    apart = {(a, b) for kind, a, b, _ in got if kind == "pair"}
    same_brand = [(a, b) for a in rows for b in rows if a[0] < b[0] and a[1] == b[1] and a[3] != b[3]]
    assert any(a[2] != b[2] for a, b in same_brand) and all(tuple(sorted((rep[a[0]], rep[b[0]]))) in apart for a, b in same_brand)


def test_random_links_have_every_encoder_and_scorer(spark, sf, monkeypatch):
    monkeypatch.setattr(learning, "QUICK", dataclasses.replace(learning.QUICK, epochs=1))
    got = {(r["model"], r["scorer"]) for r in workloads.queries()["t3_encoder_random_auc"](spark, sf).where("subset = 'all'").collect()}
    assert got == {(m, s) for m in learning.SURVEY for s in ("dot", "bilinear")}


@pytest.mark.parametrize("model", [*learning.SURVEY, "unweighted"])
def test_tiles_equal_a_row_a_neighbour(model):
    """States, losses and gradients from sums over tiles are those from one row a tile neighbour, with unlabelled rows among the neighbours."""
    r, n, d = np.random.default_rng(5), 60, 5
    tile, x, mine, e = np.sort(r.integers(0, 14, n)), r.normal(size=(n, d)), r.normal(size=(n, 4)), 50
    whose, weight, v, back = np.sort(r.integers(0, n, e)), r.random(e), r.normal(size=(e, 4)), r.normal(size=(e, d))
    near = np.array([(i, j) for i in range(n) for j in range(n) if i != j and tile[i] == tile[j]])
    mask, y = r.random(n) < 0.6, r.normal(size=n)
    x = np.hstack([x, r.normal(size=(n, 2))])
    short = encoders.Batch(x, whose, np.zeros(e, np.int64), weight, v, back, np.arange(n), tile=tile, mine=mine)
    put = lambda a, b: np.concatenate([a, b])
    long = encoders.Batch(x, put(whose, near[:, 0]), put(np.zeros(e, np.int64), np.ones(len(near), np.int64)), put(weight, np.ones(len(near))), put(v, mine[near[:, 1]]), put(back, x[near[:, 1], :d]), np.arange(n))
    w, out = {k: a + 0.05 for k, a in encoders.initial(model, d + 2, 4, 6, 1, 3).items()}, []
    for b in (short, long):
        p = {k: tape.Var(a) for k, a in w.items()}
        taken = train.take(b, mask)
        loss = encoders.contrast_loss(p, taken) if model == "contrastive" else tape.squared_error(encoders.outputs(model, p, taken, 0.1, 3), y[mask])
        loss.backward()
        out.append((loss.value, {k: q.grad for k, q in p.items() if q.grad is not None}))
    assert np.isclose(out[0][0], out[1][0]) and out[0][1].keys() == out[1][1].keys()
    assert all(np.allclose(out[0][1][k], out[1][1][k]) for k in out[0][1])
    single = dataclasses.replace(short, x=x.astype("f4"), v=v.astype("f4"), back=back.astype("f4"), mine=mine.astype("f4"))
    assert encoders.hidden("mean_pool" if model == "contrastive" else model, {k: tape.Var(a.astype("f4")) for k, a in w.items()}, train.take(single, mask), 0.1, 3).value.dtype == np.float32


def test_blocks_keep_tiles_whole(spark, sf):
    """A block has no rows for tile neighbours; a table cut through tiles has them."""
    ego = train.cut(features.ego_table(Layers(spark, sf), "height"))
    want = {r["entity_id"]: r["n"] for r in ego.selectExpr("entity_id", "size(filter(neighbours, x -> x.kind = 1)) n").collect()}
    whole, part = ([pickle.loads(r["block"]) for r in train.blocks(t).collect()] for t in (ego, ego.where("entity_id % 2 = 0")))
    seen = {}
    for b in whole:
        assert not (b.kind == 1).any() and b.agnostic.dtype == np.float32
        t = train.take(b.batch("aware"), np.ones(len(b.entity), bool))
        seen |= dict(zip(b.entity.tolist(), t.mates.degree.tolist()))
    assert seen == want and max(want.values()) > 1
    assert sum((b.kind == 1).sum() if b.tile is None else train.take(b.batch("aware"), np.ones(len(b.entity), bool)).mates.degree.sum() for b in part) == sum(n for i, n in want.items() if i % 2 == 0)
