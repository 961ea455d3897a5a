"""Training in rounds: weights go out, gradients of all runs come back summed.

A run is one (model, seed, set of folds).  One pass over the ego table works out the gradients of all runs;
they meet per run in the cluster, and the driver takes the Adam step on a few ten thousand numbers.
"""
from __future__ import annotations

import pickle
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.functions.durable import FILES_A_CORE, cut
from provgraph.learn import encoders, tape
from provgraph.learn.encoders import Batch, Mates


@dataclass(frozen=True)
class Config:
    hidden: int = 64
    epochs: int = 150
    rate: float = 0.01
    dropout: float = 0.3
    decay: float = 1e-4


@dataclass
class Run:
    """Learns from the folds in ``train``, predicts those in ``test``; with a ``scorer`` (dot or bilinear) it scores links."""

    model: str
    seed: int
    train: tuple[int, ...]
    test: tuple[int, ...]
    view: str = "aware"
    group: str = ""
    scorer: str = ""
    weights: dict = field(default_factory=dict)
    m: dict = field(default_factory=dict)
    v: dict = field(default_factory=dict)

    def learns(self, folds: np.ndarray) -> np.ndarray:
        return np.isin(folds, self.train)


def spatial_runs(models: list[str], seeds: range, folds: int = 5, group: str = "", scorer: str = "") -> list[Run]:
    """Spatial cross-validation: every row is predicted by the run that never saw its tile."""
    every = range(folds)
    return [Run(m, s, tuple(f for f in every if f != k), (k,), VIEW[m], group, scorer) for m in models for s in seeds for k in every]


#: The view of each model: agnostic ones see no source, weight or coverage features.
VIEW = {"probe": "agnostic", "mlp": "agnostic", "mean_pool": "agnostic", "attention": "agnostic", "contrastive": "agnostic", "relational": "aware", "metapath": "aware", "typed_attention": "aware", "unweighted": "aware", "aware": "aware"}


@dataclass
class Block:
    """Some rows of the ego table as flat arrays in single precision: written once, read without parsing in every epoch."""

    entity: np.ndarray
    fold: np.ndarray
    y: np.ndarray
    agnostic: np.ndarray
    aware: np.ndarray
    whose: np.ndarray
    kind: np.ndarray
    weight: np.ndarray
    v: np.ndarray
    back: np.ndarray
    pair: np.ndarray  # whose, feature, label, kind
    pair_v: np.ndarray

    tile: np.ndarray | None = None  # numbers of tiles: all others of an entity's tile are its neighbours of kind 1, which are no rows then
    mine: np.ndarray | None = None

    def batch(self, view: str) -> Batch:
        return Batch(self.agnostic if view == "agnostic" else self.aware, self.whose, self.kind, self.weight, self.v, self.back, self.entity, tile=self.tile, mine=self.mine)


#: Numbers of link kinds in the blocks.
LINK_KINDS = ["1:1", "1:n", "n:1", "n:m"]
BLOCK_ROWS = 8192
LEAST_ROWS = 256
#: Groups that the runs' gradients are summed in: a few, for each costs more than the sums.
SUMMED_IN = 8


def _lists(column: pa.ListArray, d: int) -> np.ndarray:
    """The rows of a column of arrays of ``d`` numbers, in single precision."""
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float32).reshape(len(column), d)


def _flat(rows: pa.Table) -> Block:
    get = {c: rows.column(c).combine_chunks() for c in rows.column_names}
    number = lambda c, kind: c.to_numpy(zero_copy_only=False).astype(kind)
    d, wide = len(get["x_agnostic"][0]), len(get["x_aware"][0])
    per = number(get["neighbours"].value_lengths(), np.int64)
    nbs = get["neighbours"].flatten()
    kind, whose = number(nbs.field("kind"), np.int64), np.repeat(np.arange(len(rows)), per)
    weight, v, back = number(nbs.field("weight"), float), _lists(nbs.field("v"), 4), _lists(nbs.field("back"), d)
    tile = mine = None
    if "tile" in get:
        _, tile, count = np.unique(number(get["tile"], np.int64), return_inverse=True, return_counts=True)
        near = kind == 1
        # Rows of cut tables, whose tiles aren't whole, keep a row a neighbour.
        if (np.bincount(whose[near], minlength=len(rows)) == count[tile] - 1).all() and (weight[near] == 1).all():
            mine = _lists(get["mine"], 4)
            whose, kind, weight, v, back = whose[~near], kind[~near], weight[~near], v[~near], back[~near]
        else:
            tile = None
    pairs = get["pairs"].flatten()
    kinds = np.array([LINK_KINDS.index(k) for k in pairs.field("kind").to_pylist()], np.int64)
    at = np.repeat(np.arange(len(rows)), number(get["pairs"].value_lengths(), np.int64))
    pair = np.stack([at, number(pairs.field("feature_id"), np.int64), number(pairs.field("label"), np.int64), kinds], axis=1)
    return Block(
        number(get["entity_id"], np.int64), number(get["fold"], np.int64), number(get["y"], float), _lists(get["x_agnostic"], d), _lists(get["x_aware"], wide),
        whose, kind, weight, v, back, pair, _lists(pairs.field("v"), 4), tile, mine,
    )


def _parts(rows: pa.Table, size: int) -> list[int]:
    """Ends of near equal parts of some ``size`` rows, moved on to the next tile's first row."""
    n = len(rows)
    ends = {n * i // max(1, round(n / size)) for i in range(1, max(1, round(n / size)))}
    if "tile" in rows.column_names:
        tile = rows.column("tile").to_numpy()
        first = np.append(np.flatnonzero(tile[1:] != tile[:-1]) + 1, n)
        ends = {int(first[np.searchsorted(first, e)]) for e in ends}
    return sorted(ends | {n})


def blocks(ego: DataFrame, runs: int = 1) -> DataFrame:
    """(block): the ego table in flat blocks of some BLOCK_ROWS rows, near equal ones.

    Rows are dealt by tile, if it is there, else by entity, whatever partitions they come in; a small table makes two
    blocks a core, fewer if there are several ``runs`` to be dealt out too.  A tile's rows stay together.
    """
    if "pairs" not in ego.columns:
        ego = ego.withColumn("pairs", F.array().cast("array<struct<feature_id:bigint,label:int,kind:string,v:array<double>>>"))
    cores, n = ego.sparkSession.sparkContext.defaultParallelism, ego.count()
    size = max(LEAST_ROWS, min(BLOCK_ROWS, -(-n * max(1, runs) // (2 * cores))))
    by = ["tile", "entity_id"] if "tile" in ego.columns else ["entity_id"]
    ego = ego.repartition(max(1, min(-(-n // size), FILES_A_CORE * cores)), by[0]).sortWithinPartitions(*by)

    def run(batches):
        def made(rows, ends):
            for i, j in zip([0, *ends], ends):
                if j > i:
                    yield pa.RecordBatch.from_pydict({"block": pa.array([pickle.dumps(_flat(rows.slice(i, j - i)))], pa.binary())})

        rest = None
        for batch in batches:
            rows = pa.Table.from_batches([batch])
            rest = rows if rest is None else pa.concat_tables([rest, rows])
            if len(rest) >= 8 * size:  # the last part may go on in the next batch
                ends = _parts(rest, size)[:-1]
                yield from made(rest, ends)
                rest = rest.slice(ends[-1]) if ends else rest
        if rest is not None:
            yield from made(rest, _parts(rest, size))

    return cut(ego.mapInArrow(run, "block binary"))


def dealt(flat: DataFrame, runs: int) -> tuple[DataFrame, int]:
    """(block, lot) and the number of lots: of the runs each lot takes every so many-th.

    With fewer blocks than keep the cluster busy each is there once a lot, so that small tables use all cores too.
    """
    spark = flat.sparkSession
    cores, n = spark.sparkContext.defaultParallelism, flat.count()
    lots = max(1, min(runs, -(-2 * cores // max(n, 1))))
    if lots == 1:
        return flat.withColumn("lot", F.lit(0)), 1
    parts = max(1, min(n * lots, FILES_A_CORE * cores))
    return cut(flat.crossJoin(F.broadcast(spark.range(lots).select(F.col("id").cast("int").alias("lot")))).repartition(parts)), lots


def _frozen(run: Run, cfg: Config, epoch: int) -> bool:
    """Self-supervised states are pretrained for half of the epochs and then only probed."""
    return run.model == "contrastive" and epoch >= cfg.epochs // 2


def _states(run: Run, p, b: Batch, rate: float, salt: int, frozen: bool):
    h = encoders.hidden("mean_pool" if run.model == "contrastive" else run.model, p, b, rate, salt)
    return tape.const(h.value) if frozen else h


def _loss(run: Run, p, b: Batch, y: np.ndarray, pair: np.ndarray, pair_v: np.ndarray, classes: int, cfg: Config, epoch: int):
    if run.model == "contrastive" and not _frozen(run, cfg, epoch):
        return encoders.contrast_loss(p, b)
    frozen = _frozen(run, cfg, epoch)
    h = _states(run, p, b, cfg.dropout if run.model != "probe" and not frozen else 0.0, run.seed * 100_003 + epoch, frozen)
    if run.scorer:
        return tape.logistic(encoders.link_scores(p, h, pair[:, 0], pair_v), pair[:, 2].astype(float))
    out = h @ p["head"] + p["hb"]
    return tape.cross_entropy(out, y.astype(int)) if classes else tape.squared_error(out, y)


def take(b: Batch, mask: np.ndarray) -> Batch:
    at = np.cumsum(mask) - 1
    keep = mask[b.whose]
    out = Batch(b.x[mask], at[b.whose[keep]], b.kind[keep], b.weight[keep], b.v[keep], b.back[keep], b.keys[mask])
    if b.tile is not None and mask.any():
        out.mates = Mates(b.tile, mask, b.mine, b.x[:, : b.back.shape[1]])
    return out


def _pairs_of(block: Block, mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    keep = mask[block.pair[:, 0]]
    pair = block.pair[keep].copy()
    pair[:, 0] = (np.cumsum(mask) - 1)[pair[:, 0]]
    return pair, block.pair_v[keep]


PREDICTED = "model string, seed int, grouping string, view string, entity_id long, y double, yhat double"
SCORED = "model string, seed int, grouping string, scorer string, entity_id long, feature_id long, kind string, label int, score double"


def fit(ego: DataFrame, runs: list[Run], classes: int, cfg: Config) -> DataFrame:
    """(model, seed, grouping, view, entity_id, y, yhat) of the rows that each run didn't learn from; for classes yhat is the class.

    ego: entity_id, fold, y (null: unlabelled, predicted but not learnt from), x_agnostic, x_aware, neighbours.
    Regression targets are put on the scale of each run's training rows.  Runs with a scorer learn from the
    ego rows' ``pairs`` instead, and give (model, seed, grouping, scorer, entity_id, feature_id, kind, label, score).
    """
    ego = cut(ego)
    spark, links = ego.sparkSession, bool(runs and runs[0].scorer)
    first = ego.first()
    if first is None:
        return spark.createDataFrame([], SCORED if links else PREDICTED)
    out = max(classes, 1)
    if links:
        stats = {r["fold"]: (r["n"] or 0, 0.0, 0.0) for r in ego.groupBy("fold").agg(F.sum(F.size("pairs")).alias("n")).collect()}
    else:
        stats = {r["fold"]: (r["n"], r["s"] or 0.0, r["q"] or 0.0) for r in ego.where("y is not null").groupBy("fold").agg(F.count("y").alias("n"), F.sum("y").alias("s"), F.sum(F.col("y") * F.col("y")).alias("q")).collect()}
    flat, lots = dealt(blocks(ego, len(runs)), len(runs))
    scale = []
    for r in runs:
        r.weights = encoders.initial(r.model, len(first[f"x_{r.view}"]), 4, cfg.hidden, out, r.seed, r.scorer)
        n, s, q = (sum(v[i] for f, v in stats.items() if r.learns(np.array([f]))[0]) for i in range(3))
        mean = s / n if n and not classes else 0.0
        scale.append((mean, max((q / n - mean * mean) ** 0.5, 1e-6) if n and not classes else 1.0, max(n, 1)))

    def usable(block: Block) -> np.ndarray:
        if links:
            return np.bincount(block.pair[:, 0], minlength=len(block.entity)) > 0
        return ~np.isnan(block.y)

    def gradients(sent, epoch):
        def run_all(batches):
            sums: dict[int, np.ndarray] = {}
            for pdf in batches:
                for raw, lot in zip(pdf["block"], pdf["lot"]):
                    block = pickle.loads(raw)
                    known, whole, parts = usable(block), {}, {}
                    for i, r in enumerate(sent.value):
                        if i % lots != lot:
                            continue
                        if (r.view, r.train) not in parts:  # runs that learn from the same rows share them
                            mask = known & r.learns(block.fold)
                            if r.view not in whole:
                                whole[r.view] = block.batch(r.view)
                            parts[r.view, r.train] = (mask, take(whole[r.view], mask), block.y[mask], *_pairs_of(block, mask))
                        mask, batch, y, pair, pair_v = parts[r.view, r.train]
                        if not mask.any():
                            continue
                        p = {k: tape.Var(w.astype(np.float32)) for k, w in r.weights.items()}
                        mean, sd, _ = scale[i]
                        _loss(r, p, batch, (y - mean) / sd, pair, pair_v, classes, cfg, epoch).backward()
                        g = np.concatenate([(v.grad if v.grad is not None else np.zeros_like(v.value)).ravel() for v in p.values()]).astype(float)
                        sums[i] = sums.get(i, 0) + g
            yield pd.DataFrame({"lot": [i % SUMMED_IN for i in sums], "run": list(sums), "g": [g.tobytes() for g in sums.values()]})

        return run_all

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        sums: dict[int, np.ndarray] = {}
        for i, g in zip(pdf["run"], pdf["g"]):
            sums[i] = sums.get(i, 0) + np.frombuffer(g)
        return pd.DataFrame({"run": list(sums), "g": [g.tobytes() for g in sums.values()]})

    for epoch in range(cfg.epochs):
        sent = spark.sparkContext.broadcast([Run(r.model, r.seed, r.train, r.test, r.view, r.group, r.scorer, r.weights) for r in runs])
        got = flat.mapInPandas(gradients(sent, epoch), "lot int, run int, g binary").groupBy("lot").applyInPandas(add, "run int, g binary").collect()
        for row in got:
            r, whole, i = runs[row["run"]], np.frombuffer(row["g"]) / scale[row["run"]][2], 0
            for k, w in r.weights.items():
                g = whole[i : i + w.size].reshape(w.shape)
                i += w.size
                if _frozen(r, cfg, epoch) and k not in HEAD:
                    continue
                g = g + cfg.decay * w
                r.m[k] = 0.9 * r.m.get(k, 0) + 0.1 * g
                r.v[k] = 0.999 * r.v.get(k, 0) + 0.001 * g * g
                r.weights[k] = w - cfg.rate * (r.m[k] / (1 - 0.9 ** (epoch + 1))) / (np.sqrt(r.v[k] / (1 - 0.999 ** (epoch + 1))) + 1e-8)
        sent.destroy()
    sent = spark.sparkContext.broadcast([Run(r.model, r.seed, r.train, r.test, r.view, r.group, r.scorer, r.weights) for r in runs])

    def predict(batches):
        for pdf in batches:
            for raw, lot in zip(pdf["block"], pdf["lot"]):
                block = pickle.loads(raw)
                parts = {}
                for i, r in enumerate(sent.value):
                    if i % lots != lot:
                        continue
                    if (r.view, r.test) not in parts:
                        mask = np.isin(block.fold, r.test)
                        parts[r.view, r.test] = (mask, take(block.batch(r.view), mask))
                    mask, batch = parts[r.view, r.test]
                    if not mask.any():
                        continue
                    p = {k: tape.const(w.astype(np.float32)) for k, w in r.weights.items()}
                    h = _states(r, p, batch, 0.0, 0, True)
                    if links:
                        pair, v = _pairs_of(block, mask)
                        s = encoders.link_scores(p, h, pair[:, 0], v).value[:, 0].astype(float)
                        yield pd.DataFrame({"model": r.model, "seed": r.seed, "grouping": r.group, "scorer": r.scorer, "entity_id": block.entity[mask][pair[:, 0]], "feature_id": pair[:, 1], "kind": [LINK_KINDS[k] for k in pair[:, 3]], "label": pair[:, 2], "score": s})
                        continue
                    mean, sd, _ = scale[i]
                    o = (h @ p["head"] + p["hb"]).value.astype(float)
                    yield pd.DataFrame({"model": r.model, "seed": r.seed, "grouping": r.group, "view": r.view, "entity_id": block.entity[mask], "y": block.y[mask], "yhat": o.argmax(axis=1).astype(float) if classes else o[:, 0] * sd + mean})

    return flat.mapInPandas(predict, SCORED if links else PREDICTED)


def floor(rows: DataFrame, classes: int) -> DataFrame:
    """(model, entity_id, y, yhat) of the baseline that knows labels only: per fold the others' mean, or their commonest class (ties to the smaller)."""
    rows = rows.where("y is not null")
    cells = rows.groupBy("fold", "y").agg(F.count(F.lit(1)).alias("n")) if classes else rows.groupBy("fold").agg(F.sum("y").alias("y"), F.count(F.lit(1)).alias("n"))
    own = rows.select(F.col("fold").alias("_fold")).distinct()
    others = own.join(F.broadcast(cells), F.col("_fold") != F.col("fold"))  # folds by folds and classes: a few dozen rows
    if classes:
        best = others.groupBy("_fold", "y").agg(F.sum("n").alias("n")).groupBy("_fold").agg(F.max_by("y", F.struct("n", (-F.col("y")).alias("t"))).alias("yhat"))
    else:
        best = others.groupBy("_fold").agg((F.sum("y") / F.sum("n")).alias("yhat"))
    return rows.join(F.broadcast(best), F.col("fold") == F.col("_fold")).select(F.lit("floor").alias("model"), "entity_id", "y", "yhat")


#: What a probe on frozen states learns.
HEAD = ("head", "hb", "f1", "nb_f", "f2", "bil")


def embed(ego: DataFrame, run: Run) -> DataFrame:
    """(entity_id, z): a trained run's states, for inspection."""

    def go(batches):
        for pdf in batches:
            for raw in pdf["block"]:
                block = pickle.loads(raw)
                h = _states(run, {k: tape.Var(w) for k, w in run.weights.items()}, take(block.batch(run.view), np.ones(len(block.entity), bool)), 0.0, 0, True).value.astype(float)
                yield pd.DataFrame({"entity_id": block.entity, "z": list(h)})

    return blocks(ego).mapInPandas(go, "entity_id long, z array<double>")
