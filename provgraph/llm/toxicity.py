"""Toxicity by non-negative positive-unlabelled learning.

Confirmed toxic texts are the positive sample; all texts of the training part without a label are the
unlabelled one.  With class prior p the risk p * R_p(+) + max(0, R_u(-) - p * R_p(-)) is minimised:
where the estimate of the negative part falls below zero, its gradient is turned round.  The model is
linear over words and word beginnings; its outputs are put on a probability scale with the labelled
training rows.

Of the labelled rows the fit takes at most ``positives`` toxic and ``checked`` others, the first by a hash
of the id.  Everything else covers the whole training part: how often each feature occurs, and the
unlabelled side of the risk, which tasks learn from in their own partitions, their weights being averaged
after every round.  Scoring reads every text whole.
"""
from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from provgraph.functions.columns import column, free_name, mapped, schema_with
from provgraph.functions.durable import cut_table
from provgraph.functions.ranking import hash_sample
from provgraph.llm.words import ALNUM_LOWER, U64, Block, blocks, bytes_of, hash_spans

POSITIVES, CHECKED = 6_000, 12_000
FEATURES = 800
EVIDENCE, LEAST = 3.0, 16  # standard errors that a feature stands out by; the best ones stay in any case
PREFIXES = (4, 5, 6, 7, 8, 9, 10, 12)
THRESHOLD = 0.7
#: Rounds, steps on each chunk of rows in a round, and the first round's rate.
ROUNDS, STEPS, RATE = 4, 40, 0.05
#: Rows that a task learns from at once, and that one partition is meant to hold.
CHUNK, PART_ROWS = 8192, 16_384
MOST_PARTS = 2048


def held_out(doc_id: Column) -> Column:
    """Rows whose labels are never learnt from; a null id counts as the text ''."""
    return F.crc32(F.encode(F.coalesce(doc_id.cast("string"), F.lit("")), "utf-8")) % 3 == 1


def features_of(b: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word, of, hash): each word's number among the block's different words, and the features of these: themselves and their beginnings."""
    h = b.hashes()
    _, first, word = np.unique(h, return_index=True, return_inverse=True)
    order = np.argsort(first)
    first, word = first[order], np.argsort(order)[word]
    s, e = b.s[first], b.e[first]
    size = e - s
    begun = hash_spans(b.buf, s, *[np.minimum(e, s + k) for k in PREFIXES], e)[:-1] if len(s) else []
    of, hashes = [np.arange(len(first))], [h[first]]
    for k, x in zip(PREFIXES, begun):
        long = np.flatnonzero(size > k)
        of.append(long)
        hashes.append(x[long] ^ U64(0x5851F42D4C957F2D + k))
    return word, np.concatenate(of), np.concatenate(hashes)


def occurrences(doc: np.ndarray, word: np.ndarray, of: np.ndarray, feature: np.ndarray, features: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, feature, count) from words' texts and the (word, feature) pairs."""
    o = np.argsort(of, kind="stable")
    of, feature = of[o], feature[o]
    n = np.bincount(of, minlength=int(word.max(initial=-1)) + 1)
    start = np.concatenate([[0], np.cumsum(n)])
    some = np.flatnonzero(n[word]) if len(word) else word
    reps = n[word[some]]
    at = np.repeat(start[word[some]] - np.concatenate([[0], np.cumsum(reps)])[:-1], reps) + np.arange(int(reps.sum()))
    key, count = np.unique(np.repeat(doc[some], reps) * features + feature[at], return_counts=True)
    return key // features, key % features, count


@dataclass
class Model:
    """Weights by feature hash (sorted); ``scale`` maps the margin to log-odds."""

    hashes: np.ndarray
    weight: np.ndarray  # rows: log count, square root of the rate
    bias: float
    scale: tuple[float, float]

    def __post_init__(self):
        self.maybe = np.zeros(1 << 20, bool)
        self.maybe[(self.hashes >> U64(44)).astype(np.int64)] = True

    def counted(self, b: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(text, feature, count) of the features that occur, by text."""
        if not len(self.hashes):
            return (np.empty(0, np.int64),) * 3
        word, of, h = features_of(b)
        near = np.flatnonzero(self.maybe[(h >> U64(44)).astype(np.int64)])
        k = np.minimum(np.searchsorted(self.hashes, h[near]), len(self.hashes) - 1)
        same = self.hashes[k] == h[near]
        return occurrences(b.doc(), word, of[near[same]], k[same], len(self.hashes))

    def values(self, d, n, words) -> np.ndarray:
        return np.stack([np.log1p(n), np.sqrt(100.0 * n / np.maximum(words[d], 1))])

    def margin(self, b: Block) -> np.ndarray:
        d, f, n = self.counted(b)
        out = np.full(len(b.count), self.bias)
        if len(d):
            np.add.at(out, d, (self.values(d, n, b.count) * self.weight[:, f]).sum(axis=0))
        return out

    def probability(self, margin: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.scale[0] * margin + self.scale[1], -30, 30)))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def nnpu(p: np.ndarray, u: np.ndarray, prior: float, *, w: np.ndarray | None = None, bias: float | None = None, steps: int = 300, rate: float = 0.02, decay: float = 1e-4, floor: float = 0.0) -> tuple[np.ndarray, float]:
    """Weights and bias of a linear classifier under the non-negative risk, with the logistic loss and Adam.

    ``p`` and ``u`` are the positive and the unlabelled rows (float32); every step takes all of them.
    """
    w = np.zeros(p.shape[1]) if w is None else w.astype(float)
    bias = float(np.log(prior / (1 - prior))) if bias is None else bias
    m, v = np.zeros(len(w) + 1), np.zeros(len(w) + 1)
    for t in range(1, steps + 1):
        w32 = w.astype(np.float32)
        zp, zu = (p @ w32).astype(float) + bias, (u @ w32).astype(float) + bias
        sp, su = _sigmoid(zp), _sigmoid(zu)
        negative = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
        g_plus = prior * (sp - 1) / len(p)
        g_pn, g_u = -prior * sp / len(p), su / len(u)
        gp, gu = (g_plus + g_pn, g_u) if negative >= floor else (-g_pn, -g_u)
        g = np.append(gp.astype(np.float32) @ p + gu.astype(np.float32) @ u + decay * w, gp.sum() + gu.sum())
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w, bias = w - step[:-1], bias - step[-1]
    return w, bias


def _calibrate(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Log-odds a * z + b by Newton's method, with one example's weight of smoothing; steps halve until the loss falls."""
    if len(set(y.tolist())) < 2:
        return 1.0, 0.0
    t = np.where(y == 1, (y.sum() + 1) / (y.sum() + 2), 1 / (len(y) - y.sum() + 2))
    loss = lambda a, b: (np.logaddexp(0, a * z + b) - t * (a * z + b)).sum() + 5e-4 * (a - 1) ** 2
    a, b = 1.0, 0.0
    for _ in range(50):
        q = 1 / (1 + np.exp(-np.clip(a * z + b, -30, 30)))
        d, h = q - t, np.maximum(q * (1 - q), 1e-6)
        g = np.array([(d * z).sum() + 1e-3 * (a - 1), d.sum()])
        hess = np.array([[(h * z * z).sum() + 1e-3, (h * z).sum()], [(h * z).sum(), h.sum()]])
        s, now = np.linalg.solve(hess, g), loss(a, b)
        while loss(a - s[0], b - s[1]) > now and abs(s).max() > 1e-9:
            s = s / 2
        a, b = a - s[0], b - s[1]
        if abs(s).max() < 1e-9:
            break
    return float(a), float(b)


def _candidates(positive: DataFrame, least: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash, number of positive texts) of the features in at least ``least`` of them, by hash."""

    def tally(batches):
        for batch in batches:
            for _, _, b in blocks(bytes_of(batch.column("text")), ALNUM_LOWER):
                word, of, h = features_of(b)
                known, number = np.unique(h, return_inverse=True)
                _, f, _ = occurrences(b.doc(), word, of, number, max(1, len(known)))
                yield pa.RecordBatch.from_arrays([pa.array(known.view(np.int64)), pa.array(np.bincount(f, minlength=len(known)).astype(np.int64))], ["h", "p"])

    rows = positive.select("text").mapInArrow(tally, "h long, p long").groupBy("h").agg(F.sum("p").alias("p")).where(F.col("p") >= least).toPandas()
    hashes, p = rows["h"].to_numpy(np.int64).view(U64), rows["p"].to_numpy(np.int64)
    o = np.argsort(hashes)
    return hashes[o], p[o]


def _holders(known: DataFrame, hashes: np.ndarray) -> np.ndarray:
    """The number of all training texts that hold each feature."""
    model = Model(hashes, np.zeros((2, len(hashes))), 0.0, (1.0, 0.0))
    sent = known.sparkSession.sparkContext.broadcast(model)

    def tally(batches):
        held = np.zeros(len(hashes), np.int64)
        for batch in batches:
            for _, _, b in blocks(bytes_of(batch.column("text")), ALNUM_LOWER):
                held += np.bincount(sent.value.counted(b)[1], minlength=len(held))
        some = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(held[some])], ["f", "n"])

    out = np.zeros(len(hashes), np.int64)
    for f, n in known.select("text").mapInArrow(tally, "f long, n long").groupBy("f").agg(F.sum("n")).toPandas().to_numpy():
        out[f] = n
    sent.unpersist()
    return out


def _encoded(known: DataFrame, model: Model) -> DataFrame:
    """(doc_id, words, f, n): each training text's features and their counts."""
    sent = known.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            ids = batch.column("doc_id")
            for lo, hi, b in blocks(bytes_of(batch.column("text")), ALNUM_LOWER):
                d, f, n = sent.value.counted(b)
                cut = pa.array(np.searchsorted(d, np.arange(hi - lo + 1)).astype(np.int32))
                yield pa.RecordBatch.from_arrays([ids.slice(lo, hi - lo), pa.array(b.count), *[pa.ListArray.from_arrays(cut, pa.array(x.astype(np.int32))) for x in (f, n)]], ["doc_id", "words", "f", "n"])

    return known.mapInArrow(run, "doc_id long, words long, f array<int>, n array<int>")


def _matrix(model: Model, words: np.ndarray, f, n) -> np.ndarray:
    """Rows of the encoded table as a matrix of log counts and rates, float32."""
    size = np.fromiter(map(len, f), np.int64, len(words))
    x = np.zeros((len(words), 2 * len(model.hashes)), np.float32)
    if size.sum():
        row, at = np.repeat(np.arange(len(words)), size), np.concatenate([np.asarray(y, np.int64) for y in f])
        x[row, at], x[row, at + len(model.hashes)] = model.values(row, np.concatenate([np.asarray(y, np.int64) for y in n]), words)
    return x


def _learn(model: Model, positive, unlabelled: DataFrame, prior: float, rounds: int) -> None:
    """Sets weights and bias: in each round every task learns from its own partition, and the mean by rows opens the next."""
    spark = unlabelled.sparkSession
    total = unlabelled.count()
    parts = min(MOST_PARTS, max(1, total // PART_ROWS))
    dealt = cut_table(unlabelled.repartition(parts, F.xxhash64("doc_id")))
    dealt = dealt.repartition(parts, F.xxhash64("doc_id"))  # files may be split or packed in reading
    w, bias = np.zeros(2 * len(model.hashes)), float(np.log(prior / (1 - prior)))
    fan = max(1, int(parts**0.5))
    for k in range(rounds):
        sent, rate = spark.sparkContext.broadcast((model, positive, w, bias)), RATE * 0.75**k

        def run(batches):
            from pyspark import TaskContext

            own, pos, w0, b0 = sent.value
            p, (w1, b1), n = _matrix(own, *pos), (w0, b0), 0
            for batch in batches:
                for lo in range(0, len(batch), CHUNK):
                    part = batch.slice(lo, CHUNK)
                    u = _matrix(own, part.column("words").to_numpy(), part.column("f").to_pylist(), part.column("n").to_pylist())
                    w1, b1 = nnpu(p, u, prior, w=w1, bias=b1, steps=STEPS, rate=rate)
                    n += len(u)
            if n:
                yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId() % fan], pa.int32()), pa.array([n], pa.int64()), pa.array([(np.append(w1, b1) * n).tobytes()], pa.binary())], ["g", "n", "w"])

        def add(rows: pa.Table) -> pa.Table:
            w = sum(np.frombuffer(x.as_buffer()) for x in rows.column("w"))
            return pa.table({"g": pa.array([rows.column("g")[0].as_py()], pa.int32()), "n": pa.array([sum(rows.column("n").to_pylist())], pa.int64()), "w": pa.array([w.tobytes()], pa.binary())})

        kind = "g int, n long, w binary"
        got = dealt.select("words", "f", "n").mapInArrow(run, kind).groupBy("g").applyInArrow(add, kind).orderBy("g").collect()
        sent.unpersist()
        mean = sum(np.frombuffer(bytes(r["w"])) for r in got) / sum(r["n"] for r in got)
        w, bias = mean[:-1], float(mean[-1])
    model.weight, model.bias = w.reshape(2, -1), bias


def fit(docs: DataFrame, labels: DataFrame, *, text: str = "text", positives: int = POSITIVES, checked: int = CHECKED, features: int = FEATURES, evidence: float = EVIDENCE, rounds: int = ROUNDS) -> Model:
    """Learns from rows outside the held-out part, whole texts; null ids, texts and labels give nothing to learn from.

    Features are the ``features`` strongest, those below ``evidence`` standard errors left out: with few
    toxic texts most of the others are chance, and weights on them hide the real cues.  Without a toxic
    label, or without any other row, nothing counts as toxic.
    """
    marks = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic")).withColumnRenamed("doc_id", "_id")
    known = docs.select("doc_id", column(text).alias("text")).where(~held_out(F.col("doc_id")) & F.col("text").isNotNull() & F.col("doc_id").isNotNull())
    ids = cut_table(known.select("doc_id").join(marks, F.col("doc_id") == F.col("_id"), "left").select("doc_id", "toxic"))
    count = ids.agg(F.count(F.lit(1)).alias("rows"), F.count_if(F.col("toxic") == 1).alias("pos"), F.count_if(F.col("toxic") == 0).alias("neg"), F.avg("toxic").alias("prior")).first()
    if not count["pos"] or count["pos"] == count["rows"]:
        return Model(np.empty(0, U64), np.zeros((2, 0)), -3.0, (1.0, 0.0))
    prior = min(max(float(count["prior"]), 1e-3), 0.5)
    drawn = lambda which, n, total: hash_sample(ids.where(which).select("doc_id").distinct(), [F.col("doc_id")], n, total)
    chosen = cut_table(drawn("toxic = 1", positives, count["pos"]).select(F.col("doc_id").alias("_id"), F.lit(1).alias("y")).union(drawn("toxic = 0", checked, count["neg"]).select("doc_id", F.lit(0))))
    toxic = known.join(F.broadcast(chosen.where("y = 1")), F.col("doc_id") == F.col("_id")).select("doc_id", "text")  # at most ``positives`` ids
    n_p = ids.join(F.broadcast(chosen.where("y = 1")), F.col("doc_id") == F.col("_id"), "left_semi").count()
    n_u = count["rows"] - count["pos"]
    hashes, p = _candidates(toxic, max(2, n_p // 400))
    held = _holders(known, hashes)
    share_p = p / n_p
    share_u = (np.maximum(held - share_p * count["pos"], 0) + 0.5) / n_u
    strength = (share_p - share_u) / np.sqrt((share_p + 1 / n_p) / n_p + share_u / n_u)
    best = np.lexsort((hashes, -strength))[:features]
    best = best[(np.arange(len(best)) < LEAST) | (strength[best] >= evidence)]
    model = Model(np.sort(hashes[best]), np.zeros((2, len(best))), 0.0, (1.0, 0.0))

    rows = cut_table(_encoded(known, model).join(marks, F.col("doc_id") == F.col("_id"), "left").drop("_id"))
    labelled = rows.join(F.broadcast(chosen), F.col("doc_id") == F.col("_id")).select("doc_id", "y", "words", "f", "n").toPandas()  # bounded by the two parameters
    labelled = labelled.sort_values("doc_id", kind="stable")
    part = lambda y: (lambda t: (t["words"].to_numpy(), list(t["f"]), list(t["n"])))(labelled[labelled["y"] == y])
    unlabelled = rows.where("toxic is null") if not rows.where("toxic is null").isEmpty() else rows.where("toxic = 0")
    _learn(model, part(1), unlabelled, prior, rounds)
    margins = []
    for y in (1, 0):
        words, f, n = part(y)
        for lo in range(0, len(words), CHUNK):
            margins.append((_matrix(model, words[lo : lo + CHUNK], f[lo : lo + CHUNK], n[lo : lo + CHUNK]) @ model.weight.ravel() + model.bias, y))
    z, y = np.concatenate([a for a, _ in margins]), np.concatenate([np.full(len(a), k) for a, k in margins])
    model.scale = _calibrate(z, y)
    return model


def score(docs: DataFrame, model: Model, *, text: str = "text", out: str = "score") -> DataFrame:
    """``docs`` with the probability ``out`` that the text is toxic; a null text scores as an empty one, a column named as ``out`` is replaced."""
    docs = docs.select(*[column(c) for c in docs.columns if c.lower() != out.lower()])
    names, at = docs.columns, docs.columns.index(text)
    schema = schema_with(docs, **{out: "double"})
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            got = [sent.value.probability(sent.value.margin(b)) for _, _, b in blocks(bytes_of(batch.column(at)), ALNUM_LOWER)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.concatenate(got) if got else np.empty(0))], [*names, out])

    return mapped(docs, run, schema)


def digest(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """doc_id, held_out, score and predicted (score >= 0.7) of every document; equal rows stay separate."""
    scored = score(docs.select("doc_id", "text"), fit(docs, labels, **options))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """``docs`` without those whose score reaches the threshold; same columns, whatever their names; null and repeated rows are scored like all others."""
    out = free_name(docs.columns, "score")
    return score(docs, fit(docs, labels, **options), out=out).where(F.col(out) < THRESHOLD).select(*map(column, docs.columns))
