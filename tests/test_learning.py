import numpy as np
import pytest

from provgraph.functions import statistics
from provgraph.learn import encoders, metrics, tape
from provgraph.learn.encoders import Batch


def batch(n=7, e=15, seed=0):
    r = np.random.default_rng(seed)
    return Batch(r.normal(size=(n, 5)), r.integers(0, n - 1, e), r.integers(0, 2, e), r.random(e), r.normal(size=(e, 4)), r.normal(size=(e, 5)), np.arange(n))


@pytest.mark.parametrize("model", ["probe", "mlp", "mean_pool", "attention", "relational", "metapath", "typed_attention", "unweighted", "aware", "contrastive"])
def test_gradients(model):
    b, y = batch(), np.random.default_rng(1).normal(size=7)
    w = encoders.initial(model, 5, 4, 6, 1, 3)
    w = {k: v + 0.05 for k, v in w.items()}

    def loss(w):
        p = {k: tape.Var(v) for k, v in w.items()}
        out = encoders.contrast_loss(p, b) if model == "contrastive" else tape.squared_error(encoders.outputs(model, p, b), y)
        return out, p

    out, p = loss(w)
    out.backward()
    for k in w:
        if p[k].grad is None:
            continue
        if model == "contrastive" and k in ("head", "hb", "self1", "b1", "self2", "b2") or model == "contrastive" and k != "disc":
            continue  # the readout is held constant, so only the discriminator's slope is exact
        i = (0, 0)
        up, down = ({**w, k: w[k] + d * (np.indices(w[k].shape).sum(axis=0) == 0)} for d in (1e-6, -1e-6))
        assert abs((loss(up)[0].value - loss(down)[0].value) / 2e-6 - p[k].grad[i]) < 1e-3 * max(1, abs(p[k].grad[i])), k


def test_unit_weights_and_tied_matrices_are_mean_pooling():
    b = batch()
    tied = encoders.initial("mean_pool", 5, 4, 6, 1, 2)
    typed = {k: v for k, v in tied.items() if not k.endswith("_all")} | {f"{k[:-4]}_{s}": v for k, v in tied.items() if k.endswith("_all") for s in (0, 1)}
    var = lambda w: {k: tape.Var(v) for k, v in w.items()}
    one = Batch(b.x, b.whose, b.kind, np.ones(len(b.kind)), b.v, b.back, b.keys)
    a = encoders.outputs("mean_pool", var(tied), b).value
    assert np.allclose(a, encoders.outputs("aware", var(typed), one).value) and np.allclose(a, encoders.outputs("unweighted", var(typed), b).value)
    assert not np.allclose(a, encoders.outputs("aware", var(typed), b).value)


def test_zero_weights_leave_the_self_term():
    b = batch()
    b.weight[:] = 0
    assert np.isfinite(encoders.outputs("aware", {k: tape.Var(v) for k, v in encoders.initial("aware", 5, 4, 6, 1, 2).items()}, b).value).all()


def test_dropout_repeats():
    x = tape.Var(np.ones((50, 20)))
    a, b = (encoders.dropout(x, 0.3, np.arange(50), 5).value for _ in range(2))
    assert (a == b).all() and 0.2 < (a == 0).mean() < 0.4


def test_metrics(spark):
    p = spark.createDataFrame([("m", 0.0, 0.0), ("m", 0.0, 1.0), ("m", 1.0, 1.0), ("m", 2.0, 1.0), ("m", None, 1.0)], "model string, y double, yhat double")
    assert abs(metrics.macro_f1(p, ["model"]).first()["value"] - (2 / 3 + 0.5 + 0) / 3) < 1e-12
    q = spark.createDataFrame([("m", 1.0, 1.0), ("m", 3.0, 2.0)], "model string, y double, yhat double")
    assert metrics.r2(q, ["model"]).first()["value"] == 0.5
    assert metrics.r2(spark.createDataFrame([("m", 1.0, 2.0)], "model string, y double, yhat double"), ["model"]).first()["value"] is None
    s = spark.createDataFrame([("g", 1, 0.9), ("g", 1, 0.5), ("g", 0, 0.5), ("g", 0, 0.1)], "g string, label int, score double")
    assert metrics.auc(s, ["g"]).first()["auc"] == (2 + 1.5) / 4


def test_statistics():
    assert abs(statistics.t_quantile(0.975, 9) - 2.262157) < 1e-4
    assert abs(statistics.t_two_sided(2.262157, 9) - 0.05) < 1e-5
    assert statistics.signed_rank([1.0] * 10) == 2 / 1024 and statistics.signed_rank([0.0]) is None
    r = statistics.paired([1, 2, 3, 4], [1.1, 2.2, 3.1, 4.2])
    assert r["verdict"] == "difference" and r["lo"] < 0.15 < r["hi"]
    assert statistics.paired([1, 2], [1, 2])["verdict"] == "null"
    assert statistics.paired([1, 2], [2, 3])["verdict"] == "constant difference"


@pytest.mark.parametrize("scorer", ["dot", "bilinear"])
def test_link_gradients(scorer):
    b, r = batch(), np.random.default_rng(2)
    w = {k: v + 0.05 for k, v in encoders.initial("aware", 5, 4, 6, 1, 3, scorer).items()}
    whose, v, y = r.integers(0, 7, 12), r.normal(size=(12, 4)), r.integers(0, 2, 12).astype(float)

    def loss(w):
        p = {k: tape.Var(x) for k, x in w.items()}
        return tape.logistic(encoders.link_scores(p, encoders.hidden("aware", p, b), whose, v), y), p

    out, p = loss(w)
    out.backward()
    for k in w:
        if k in ("head", "hb"):
            continue
        up, down = ({**w, k: w[k] + d * (np.indices(w[k].shape).sum(axis=0) == 0)} for d in (1e-6, -1e-6))
        assert abs((loss(up)[0].value - loss(down)[0].value) / 2e-6 - p[k].grad[0, 0]) < 1e-3 * max(1, abs(p[k].grad[0, 0])), k


def test_contrastive_gradients_reach_the_encoder():
    b = batch()
    w = {k: v + 0.05 for k, v in encoders.initial("contrastive", 5, 4, 6, 1, 3).items()}
    loss = lambda w: encoders.contrast_loss({k: tape.Var(v) for k, v in w.items()}, b)
    p = {k: tape.Var(v) for k, v in w.items()}
    encoders.contrast_loss(p, b).backward()
    for k in ("disc", "self2", "n2_all"):
        up, down = ({**w, k: w[k] + d * (np.indices(w[k].shape).sum(axis=0) == 0)} for d in (1e-6, -1e-6))
        assert abs((loss(up).value - loss(down).value) / 2e-6 - p[k].grad[0, 0]) < 1e-3 * max(1, abs(p[k].grad[0, 0])), k


def test_auc_in_ranges(spark):
    r = np.random.default_rng(0)
    rows = [(g, int(y), float(round(r.normal() + y, 2))) for g in "ab" for y in r.integers(0, 2, 900)]
    got = {x["g"]: x["auc"] for x in metrics.auc(spark.createDataFrame(rows, "g string, label int, score double"), ["g"]).collect()}
    for g in "ab":
        pos, neg = ([s for h, y, s in rows if h == g and y == k] for k in (1, 0))
        assert abs(got[g] - np.mean([(p > n) + (p == n) / 2 for p in pos for n in neg])) < 1e-9


def test_frozen_probes_and_links_train(spark):
    """Links told by a feature that the entity's neighbourhood shows are learnt; frozen states don't move while they are probed."""
    from provgraph.learn import train

    r = np.random.default_rng(1)
    rows = []
    for i in range(240):
        side = float(i % 2)
        pairs = [(i * 10 + k, int(k % 2 == side), "1:1", [float(k % 2), 0.0, 0.0, r.random()]) for k in range(4)]
        rows.append((i, 0, i % 5, side, [side, r.random()], [side, r.random(), 1.0], [], pairs))
    kinds = "entity_id long, city int, fold int, y double, x_agnostic array<double>, x_aware array<double>, neighbours array<struct<kind:int,weight:double,v:array<double>,back:array<double>>>, pairs array<struct<feature_id:bigint,label:int,kind:string,v:array<double>>>"
    ego = spark.createDataFrame(rows, kinds)
    cfg = train.Config(hidden=8, epochs=30, rate=0.05, dropout=0.0)
    scored = train.fit(ego, train.spatial_runs(["mlp"], range(1), scorer="bilinear"), 0, cfg)
    assert metrics.auc(scored, ["model"]).first()["auc"] > 0.9 and scored.count() == 960
    runs = train.spatial_runs(["contrastive"], range(1))
    seen = []
    train.fit(ego, runs, 2, train.Config(hidden=8, epochs=4, rate=0.05, dropout=0.0))
    seen.append(runs[0].weights["self1"].copy())
    again = train.spatial_runs(["contrastive"], range(1))
    train.fit(ego, again, 2, train.Config(hidden=8, epochs=8, rate=0.05, dropout=0.0))
    # Half of the epochs pretrain: two against four steps differ, but the first two are the same ones.
    assert not np.allclose(seen[0], again[0].weights["self1"]) and not np.allclose(again[0].weights["head"], train.encoders.initial("contrastive", 2, 4, 8, 2, 0)["head"])
