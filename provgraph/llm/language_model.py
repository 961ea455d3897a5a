"""A gated recurrent language model that scores whole documents.

Words fall into classes by their corpus count: the commonest words into small head classes, all
others into tail classes of near equal share.  The network predicts the class, and inside a head class
the word, from its state; inside a tail class a word has its share of the class's corpus counts.
Every word of every size of vocabulary has a probability, words never seen in training share one.
The state runs on from window to window, so that a document's log-likelihood covers it completely.

Counts, vocabulary, classes and the network come from all training documents, whole.  Counts reach a
task as the few that its own documents need: documents are dealt into batches of bounded size, each
batch asks for its distinct words, and the answers meet the batch, which is written as two bytes a
token.  The network learns from that table in rounds: each task runs truncated back-propagation over
its part of the round's documents from the common weights, and the mean of the tasks' weights by
tokens opens the next round.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from provgraph.functions.durable import cut_table
from provgraph.functions.ranking import first_rows
from provgraph.llm.words import BLANK_LOWER, U64, Block, blocks, bytes_of

STATE = 16
HEAD_CLASSES, HEAD_SIZE = 16, 32
TAIL_CLASSES = 24
WINDOW = 24
PASSES, ROUNDS, RATE = 1, 2, 0.02
LANES = 192
CHUNK, STEP_TOKENS = 1 << 20, 1 << 22  # tokens learnt from, and scored, at once; a longer document is a chunk of its own
#: Texts that ask for their counts together, and such batches in a task.
BATCH_BYTES, BATCHES_A_TASK = 8 << 20, 4
POOL = 1 << 19  # hashes that are held before they are made distinct
END = np.int64(0)
END_HASH = U64(0x1234567)
KIND = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])
CLASSES = HEAD_CLASSES + TAIL_CLASSES + 1  # the last: words never seen in training
RARE = np.uint16(1 << 15)  # marks a token that stands for the unseen ones while the network learns


def held_out(doc_id: Column) -> Column:
    """Documents never learnt from; a null id counts as the text ''."""
    return F.crc32(F.encode(F.coalesce(doc_id.cast("string"), F.lit("")), "utf-8")) % 7 == 2


class Network:
    """Gated recurrent unit with class-factored output; float32."""

    def __init__(self, state: int, seed: int = 1):
        rng = np.random.default_rng(seed)
        d = state
        inputs = HEAD_CLASSES * HEAD_SIZE + TAIL_CLASSES + 1
        self.p = {
            "E": rng.normal(0, 0.3, (inputs, 3 * d)),  # input words as their contribution to the gates
            "U": rng.normal(0, d**-0.5, (d, 2 * d)),
            "V": rng.normal(0, d**-0.5, (d, d)),
            "b": np.zeros(3 * d),
            "C": np.zeros((d, CLASSES)),
            "c": np.zeros(CLASSES),
            "W": np.zeros((HEAD_CLASSES, d, HEAD_SIZE)),
            "w": np.zeros((HEAD_CLASSES, HEAD_SIZE)),
        }
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}
        self.d = d

    @staticmethod
    def symbol(cls: np.ndarray, item: np.ndarray) -> np.ndarray:
        """The input row of a word: its own in a head class, its class's otherwise."""
        return np.where(cls < HEAD_CLASSES, cls * HEAD_SIZE + item, HEAD_CLASSES * HEAD_SIZE - HEAD_CLASSES + cls)

    @staticmethod
    def place(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(class, item) of input rows: the inverse of ``symbol``."""
        x = x.astype(np.int64)
        head = x < HEAD_CLASSES * HEAD_SIZE
        return np.where(head, x // HEAD_SIZE, x - HEAD_CLASSES * HEAD_SIZE + HEAD_CLASSES), np.where(head, x % HEAD_SIZE, 0)

    def step(self, x: np.ndarray, h: np.ndarray, g: np.ndarray | None = None):
        """The next state and the gates; ``g``: what the words give to the gates, if that is known already."""
        d, p = self.d, self.p
        g = p["E"][x] + p["b"] if g is None else g
        a = h @ p["U"]
        a += g[:, : 2 * d]
        np.negative(a, out=a)
        np.clip(a, -30, 30, out=a)
        np.exp(a, out=a)
        a += 1
        np.reciprocal(a, out=a)
        z, r = a[:, :d], a[:, d:]
        n = (r * h) @ p["V"]
        n += g[:, 2 * d :]
        np.tanh(n, out=n)
        new = n - h
        new *= z
        new += h
        return new, z, r, n

    def outputs(self, h: np.ndarray, cls: np.ndarray, item: np.ndarray, grad: dict | None = None):
        """Natural log-probability of class and, in head classes, word; with ``grad`` also the gradient of the loss at h."""
        p = self.p
        e = np.exp(np.minimum(h @ p["C"] + p["c"], 60))
        q = e / e.sum(axis=1, keepdims=True)
        rows = np.arange(len(h))
        out = np.log(q[rows, cls] + 1e-30)
        if grad is not None:
            q[rows, cls] -= 1
            grad["C"] += h.T @ q
            grad["c"] += q.sum(axis=0)
            dh = q @ p["C"].T
        small = cls.astype(np.uint8)  # sorted by radix
        order = np.argsort(small, kind="stable")
        ends = np.searchsorted(small[order], np.arange(HEAD_CLASSES + 1, dtype=np.uint8))
        for c in range(HEAD_CLASSES):
            at = order[ends[c] : ends[c + 1]]
            if not len(at):
                continue
            e = np.exp(np.minimum(h[at] @ p["W"][c] + p["w"][c], 60))
            q = e / e.sum(axis=1, keepdims=True)
            k = np.arange(len(at))
            out[at] += np.log(q[k, item[at]] + 1e-30)
            if grad is not None:
                q[k, item[at]] -= 1
                grad["W"][c] += h[at].T @ q
                grad["w"][c] += q.sum(axis=0)
                dh[at] += q @ p["W"][c].T
        return (out, dh) if grad is not None else out

    def gradients(self, x: np.ndarray, cls: np.ndarray, item: np.ndarray, live: np.ndarray, h: np.ndarray, new: np.ndarray | None = None):
        """Loss, gradients and last state of one window (time, lanes); ``live`` marks real words, ``new`` first words of documents, whose state is zero; the gradient stops there and at the window's start."""
        d, p = self.d, self.p
        fresh = np.zeros(len(x), bool) if new is None else new.any(axis=1)
        grad = {k: np.zeros_like(v) for k, v in p.items()}
        past, kept, whole = [], [], live.all()
        given = p["E"][x] + p["b"]
        for t in range(len(x)):
            if fresh[t]:
                h = np.where(new[t][:, None], 0, h).astype(h.dtype)
            past.append(h)
            after, z, r, n = self.step(x[t], h, given[t])
            h = after if whole else np.where(live[t][:, None], after, h)
            kept.append((z, r, n))
        m = live.ravel()
        # Word t is predicted from the state before it is read.
        before = np.concatenate(past)
        if whole:
            logp, full = self.outputs(before, cls.ravel(), item.ravel(), grad)
        else:
            logp, dh_out = self.outputs(before[m], cls.ravel()[m], item.ravel()[m], grad)
            full = np.zeros_like(before)
            full[m] = dh_out
        full = full.reshape(len(x), -1, d)
        dh = np.zeros_like(h)
        z, r, n = (np.stack([k[i] for k in kept]) for i in range(3))
        h0, stay = np.stack(past), 1 - z
        to_n, to_z, to_r, reset = z * (1 - n * n), (n - h0) * z * stay, h0 * r * (1 - r), r * h0
        gates = np.zeros((*x.shape, 3 * d), h.dtype)
        v_t, u_t = p["V"].T.copy(), p["U"].T.copy()
        for t in reversed(range(len(x))):
            g = gates[t]
            dn = dh * to_n[t]
            rh = dn @ v_t
            g[:, :d] = dh * to_z[t]
            g[:, d : 2 * d] = rh * to_r[t]
            g[:, 2 * d :] = dn
            if not whole:
                g *= live[t][:, None]
            down = g[:, : 2 * d] @ u_t
            rh *= r[t]
            down += rh
            down += dh * stay[t]
            dh = down if whole else np.where(live[t][:, None], down, dh)
            dh += full[t]
            if fresh[t]:
                dh = np.where(new[t][:, None], 0, dh).astype(dh.dtype)
        gates, rows = gates.reshape(-1, 3 * d), x.ravel()
        grad["V"] += reset.reshape(-1, d).T @ gates[:, 2 * d :]
        grad["U"] += before.T @ gates[:, : 2 * d]
        grad["b"] += gates.sum(axis=0)
        o = np.argsort(rows.astype(np.uint16), kind="stable")
        at = np.flatnonzero(np.diff(rows[o], prepend=-1))
        grad["E"][rows[o][at]] += np.add.reduceat(gates[o], at, axis=0)
        return -logp.sum(), int(m.sum()), grad, h

    def prepare(self, counts: tuple[np.ndarray, np.ndarray]) -> None:
        """Output biases from the corpus counts of classes and head words."""
        self.p["c"] += np.log(counts[0] + 1).astype(np.float32)
        self.p["w"] += np.log(counts[1] + 1).astype(np.float32)
        self.t, self.m, self.v = 0, *({k: np.zeros_like(x) for k, x in self.p.items()} for _ in "mv")

    def learn(self, docs: list[np.ndarray], rate: float) -> int:
        """One pass over documents (input rows, each ending with the end); lanes read them one after another, the state is cleared between them."""
        p, m, v = self.p, self.m, self.v
        x = np.concatenate(docs)
        total, size = len(x), -(-len(x) // LANES)
        new = np.zeros(total, bool)
        new[np.cumsum([0, *(len(d) for d in docs[:-1])])] = True
        fill = lambda a: np.concatenate([a, np.zeros(size * LANES - total, a.dtype)]).reshape(LANES, size).T
        live, x, new = fill(np.ones(total, bool)), fill(x), fill(new)
        h = np.zeros((LANES, self.d), np.float32)
        for at in range(0, size, WINDOW):
            s = slice(at, at + WINDOW)
            cls, item = self.place(x[s])
            _, n, grad, h = self.gradients(x[s].astype(np.int64), cls, item, live[s], h, new[s])
            self.t += 1
            for key in p:
                g = np.clip(grad[key] / max(n, 1) * 20, -1, 1)
                m[key] += 0.1 * (g - m[key])
                v[key] += 0.01 * (g * g - v[key])
                p[key] -= rate * (m[key] / (1 - 0.9**self.t)) / (np.sqrt(v[key] / (1 - 0.99**self.t)) + 1e-6)
        return total

    def flat(self) -> np.ndarray:
        return np.concatenate([x.ravel() for x in self.p.values()])

    def unflat(self, weights: np.ndarray) -> None:
        at = 0
        for k, x in self.p.items():
            self.p[k] = weights[at : at + x.size].reshape(x.shape).astype(np.float32)
            at += x.size

    def log_likelihood(self, docs: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        """``likelihoods`` of documents given as classes and items."""
        return self.likelihoods([self.symbol(c, i).astype(np.uint16) for c, i in docs])

    def likelihoods(self, docs: list[np.ndarray]) -> np.ndarray:
        """Natural log-likelihood of each document's classes and head words, from its input rows; documents run in step, longest first."""
        size = np.array([len(x) for x in docs])
        order = np.argsort(-size, kind="stable")
        out = np.zeros(len(docs))
        h = np.zeros((len(docs), self.d), np.float32)
        t, top = 0, int(size.max(initial=0))
        flat = np.concatenate([docs[i] for i in order]) if len(docs) else np.empty(0, np.uint16)
        base, falling = np.concatenate([[0], np.cumsum(size[order])])[:-1], -size[order]
        while t < top:
            states, read, lanes, budget = [], [], [], 0
            while t < top and budget < 32_768:
                live = int(np.searchsorted(falling, -t, "left"))
                h = h[:live]
                x = flat[base[:live] + t].astype(np.int64)
                states.append(h)
                read.append(x)
                lanes.append(live)
                h = self.step(x, h)[0]
                t += 1
                budget += live
            got = self.outputs(np.concatenate(states), *self.place(np.concatenate(read)))
            who = np.concatenate([np.arange(n) for n in lanes])
            out[order] += np.bincount(who, got, len(docs))
        return out


class Vocabulary:
    """Class and item of a word from its hash and count; bounded: head words one by one, tail classes as count ranges."""

    def __init__(self, head: list[tuple[int, int]], edges: np.ndarray, mass: np.ndarray, words: int, tokens: int):
        self.tokens, self.words, self.edges, self.mass = tokens, words, edges, mass
        h = np.array([x for x, _ in head], np.int64).view(U64)
        rank = np.arange(len(h))
        o = np.argsort(h)
        self.hash, self.rank = h[o], rank[o]
        sizes = np.zeros((HEAD_CLASSES, HEAD_SIZE))
        for r, (_, n) in enumerate(head):
            sizes[r // HEAD_SIZE, r % HEAD_SIZE] = n
        self.head_counts = sizes

    def place(self, h: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(class, item, log10 of the fixed share inside a tail class) of words with these training counts."""
        tail = HEAD_CLASSES + np.searchsorted(self.edges, -count, "left")
        cls = np.where(count > 0, np.minimum(tail, CLASSES - 2), CLASSES - 1)
        share = np.where(count > 0, np.log10((count + 1) / self.mass[np.clip(cls - HEAD_CLASSES, 0, TAIL_CLASSES - 1)]), 0.0)
        item = np.zeros(len(h), np.int64)
        if len(self.hash):
            k = np.minimum(np.searchsorted(self.hash, h), len(self.hash) - 1)
            head = self.hash[k] == h
            cls = np.where(head, self.rank[k] // HEAD_SIZE, cls)
            item = np.where(head, self.rank[k] % HEAD_SIZE, 0)
            share = np.where(head, 0.0, share)
        return cls, item, share

    def base(self, count: np.ndarray) -> np.ndarray:
        return np.log10((count + 1) / (self.tokens + self.words + 1))


def _tokens(b: Block) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, first): each text's words and then the end."""
    h = b.hashes()
    n = len(b.count)
    at = np.arange(len(h)) + b.doc()
    out = np.full(len(h) + n, END_HASH, U64)
    out[at] = h
    return out, np.concatenate([[0], np.cumsum(b.count + 1)])


def count_tokens(docs: DataFrame) -> DataFrame:
    """(h, n): the count of every distinct token of ``docs`` (column text); summed in the task first."""

    def run(batches):
        for batch in batches:
            pool = [_tokens(b)[0] for _, _, b in blocks(bytes_of(batch.column("text")), BLANK_LOWER)]
            h, n = np.unique(np.concatenate(pool), return_counts=True) if pool else (np.empty(0, U64), np.empty(0, np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(n.astype(np.int64))], ["h", "n"])

    return docs.select("text").mapInArrow(run, "h long, n long").groupBy("h").agg(F.sum("n").alias("n"))


def build_vocabulary(counts: DataFrame) -> Vocabulary:
    """Head words and tail classes from all counts; the driver gets a table of distinct counts and the head."""
    head = [(r["h"], r["n"]) for r in first_rows(counts, [F.desc("n"), F.col("h")], HEAD_CLASSES * HEAD_SIZE, [F.col("h")]).collect()]
    chosen = counts.sparkSession.createDataFrame(head or [(0, 0)], "h long, x long").select(F.col("h").alias("_h"))
    tail = counts.join(F.broadcast(chosen), F.col("h") == F.col("_h"), "left_anti")
    # Counts to two significant digits: at most a few thousand rows however large the corpus.
    digits = F.pow(F.lit(10.0), F.greatest(F.floor(F.log10("n")) - 1, F.lit(0)))
    spread = sorted(((int(r["g"]), r["w"], int(r["s"])) for r in tail.groupBy((F.floor(F.col("n") / digits) * digits).cast("long").alias("g")).agg(F.count(F.lit(1)).alias("w"), F.sum(F.col("n") + 1).alias("s")).collect()), reverse=True)
    whole = counts.agg(F.sum("n").alias("t"), F.count(F.lit(1)).alias("v")).first()
    total, acc, edges, mass = sum(s for *_, s in spread), 0, [], [0.0]
    for g, _, s in spread:
        acc += s
        mass[-1] += s
        if acc >= total / TAIL_CLASSES * (len(edges) + 1) and len(edges) < TAIL_CLASSES - 1:
            edges.append(-g)
            mass.append(0.0)
    mass = [max(m, 1.0) for m in mass] + [1.0] * (TAIL_CLASSES - len(mass))
    return Vocabulary(head, np.array(edges, np.int64), np.array(mass), whole["v"], whole["t"] or 0)


def _ask(dealt: DataFrame) -> DataFrame:
    """(batch, h): the distinct tokens of each batch; a batch is in one task, and all columns stay, so that its texts are shuffled once."""

    def run(batches):
        pool: dict[int, list[np.ndarray]] = {}
        for batch in batches:
            lots = batch.column("batch").to_numpy()
            for lo, hi, b in blocks(bytes_of(batch.column("text")), BLANK_LOWER):
                h, first = _tokens(b)
                lot = np.repeat(lots[lo:hi], np.diff(first))
                order = np.argsort(lot, kind="stable")
                h, names, at = h[order], *np.unique(lot[order], return_index=True)
                for x, part in zip(names.tolist(), np.split(h, at[1:])):
                    held = pool.setdefault(x, [])
                    held.append(np.unique(part))
                    if sum(map(len, held)) > POOL + 2 * len(held[0]):
                        pool[x] = [np.unique(np.concatenate(held))]
        for x, held in pool.items():
            u = np.unique(np.concatenate(held))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(u), x, np.int32)), pa.array(u.view(np.int64))], ["batch", "h"])

    return dealt.mapInArrow(run, "batch int, h long")


def _lookup(sorted_h: np.ndarray, n: np.ndarray, h: np.ndarray) -> np.ndarray:
    if not len(sorted_h):
        return np.zeros(len(h), np.int64)
    k = np.minimum(np.searchsorted(sorted_h, h), len(sorted_h) - 1)
    return np.where(sorted_h[k] == h, n[k], 0)


def mix_bit(h: np.ndarray) -> np.ndarray:
    """One in eight, by hash."""
    return (h >> U64(20)) & U64(7) == 0


ENCODED = "doc_id long, held_out boolean, learnt boolean, n_tokens long, n_known long, base_score double, fixed double, tokens binary"


def encode(docs: DataFrame, counts: DataFrame, vocabulary: Vocabulary, *, batch_bytes: int = BATCH_BYTES) -> DataFrame:
    """Every row with its tokens as input rows of the network, two bytes each, and what counts alone tell: n_known, base_score, and the fixed shares inside tail classes."""
    size = docs.agg(F.sum(F.coalesce(F.octet_length("text"), F.lit(0)) + 8)).first()[0] or 1
    lots = max(1, -(-size // batch_bytes))
    dealt = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text", F.pmod(F.xxhash64("doc_id", "text"), F.lit(lots)).cast("int").alias("batch")).repartition(max(1, int(lots) // BATCHES_A_TASK), "batch")
    asked = _ask(dealt).join(counts, "h").select("batch", "h", "n")
    sent = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        vocabulary = sent.value
        h, n = right.column("h").to_numpy().view(U64), right.column("n").to_numpy()
        o = np.argsort(h)
        h, n = h[o], n[o]
        out = []
        for batch in left.to_batches():
            null = batch.column("text").is_null().to_numpy(zero_copy_only=False)
            for lo, hi, b in blocks(bytes_of(batch.column("text")), BLANK_LOWER):
                t, first = _tokens(b)
                c = _lookup(h, n, t)
                cls, item, share = vocabulary.place(t, c)
                # A word that training saw once stands for those that it never sees.
                rare = vocabulary.place(t, np.where((c == 1) & mix_bit(t), 0, c))[0] != cls
                x = Network.symbol(cls, item).astype(np.uint16) | np.where(rare, RARE, np.uint16(0))
                doc = np.repeat(np.arange(hi - lo), np.diff(first))
                add = lambda v: np.bincount(doc, v, hi - lo)
                raw = x.astype("<u2").tobytes()
                out.append(pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(lo, hi - lo), batch.column("held_out").slice(lo, hi - lo), pa.array([not z and not y for z, y in zip(batch.column("held_out").slice(lo, hi - lo).to_pylist(), null[lo:hi])], pa.bool_()),
                     pa.array(np.diff(first).astype(np.int64)), pa.array(add(c > 0).astype(np.int64)), pa.array(add(vocabulary.base(c))), pa.array(add(share)), pa.array([raw[2 * i : 2 * j] for i, j in zip(first[:-1], first[1:])], pa.binary())],
                    ["doc_id", "held_out", "learnt", "n_tokens", "n_known", "base_score", "fixed", "tokens"],
                ))
        if out:
            return pa.Table.from_batches(out)
        kinds = [pa.int64(), pa.bool_(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary()]
        return pa.table([pa.array([], k) for k in kinds], ["doc_id", "held_out", "learnt", "n_tokens", "n_known", "base_score", "fixed", "tokens"])

    return dealt.groupBy("batch").cogroup(asked.groupBy("batch")).applyInArrow(run, ENCODED)


def fit(encoded: DataFrame, vocabulary: Vocabulary, *, state: int = STATE, passes: int = PASSES, rounds: int = ROUNDS, rate: float = RATE) -> Network:
    """Learns from every token of the rows that are ``learnt``, ``passes`` times, each time in ``rounds`` parts by hash."""
    net = Network(state)
    net.prepare((np.concatenate([vocabulary.head_counts.sum(axis=1), vocabulary.mass, [1.0]]), vocabulary.head_counts))
    unseen = Network.symbol(np.array(CLASSES - 1), np.array(0)).astype(np.uint16)
    part = F.pmod(F.xxhash64("doc_id", "n_tokens", "base_score"), F.lit(rounds))
    fan = max(1, int(encoded.rdd.getNumPartitions() ** 0.5))
    for k in range(passes * rounds):
        sent, speed = encoded.sparkSession.sparkContext.broadcast(net), rate * 0.5 ** (k // rounds)

        def run(batches):
            from pyspark import TaskContext

            own, total, chunk, held = sent.value, 0, [], 0
            for batch in batches:
                for raw in batch.column(0):
                    x = np.frombuffer(raw.as_buffer(), "<u2")
                    chunk.append(np.where(x & RARE, unseen, x))
                    held += len(x)
                    if held >= CHUNK:
                        total += own.learn(chunk, speed)
                        chunk, held = [], 0
            if chunk:
                total += own.learn(chunk, speed)
            if total:
                yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId() % fan], pa.int32()), pa.array([total], pa.int64()), pa.array([(own.flat().astype(np.float64) * total).tobytes()], pa.binary())], ["g", "n", "w"])

        def add(rows: pa.Table) -> pa.Table:
            w = sum(np.frombuffer(x.as_buffer()) for x in rows.column("w"))
            return pa.table({"g": pa.array([rows.column("g")[0].as_py()], pa.int32()), "n": pa.array([sum(rows.column("n").to_pylist())], pa.int64()), "w": pa.array([w.tobytes()], pa.binary())})

        kind = "g int, n long, w binary"
        # Weights of a task are a few hundred kilobytes; the driver gets as many as the root of the tasks.
        got = encoded.where(F.col("learnt") & (part == k % rounds)).select("tokens").mapInArrow(run, kind).groupBy("g").applyInArrow(add, kind).orderBy("g").collect()
        sent.unpersist()
        if got:
            net.unflat(sum(np.frombuffer(bytes(r["w"])) for r in got) / sum(r["n"] for r in got))
    return net


def score(encoded: DataFrame, vocabulary: Vocabulary, net: Network) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) for every row."""
    sent = encoded.sparkSession.sparkContext.broadcast(net)
    known = vocabulary.tokens

    def run(batches):
        for batch in batches:
            size = np.cumsum(batch.column("n_tokens").to_numpy())
            lo = 0
            while lo < len(size):
                hi = max(lo + 1, int(np.searchsorted(size, (size[lo - 1] if lo else 0) + STEP_TOKENS, "right")))
                rows = batch.slice(lo, hi - lo)
                docs = [np.frombuffer(x.as_buffer(), "<u2") & ~RARE for x in rows.column("tokens")]
                ll = sent.value.likelihoods(docs) / np.log(10) + rows.column("fixed").to_numpy()
                names = ["doc_id", "held_out", "n_tokens", "n_known", "base_score"]
                doc, out, n, seen, base = (rows.column(c) for c in names)
                yield pa.RecordBatch.from_arrays([doc, out, n, seen, pa.array(np.full(hi - lo, known, np.int64)), base, pa.array(ll)], KIND.names)
                lo = hi

    return encoded.mapInArrow(run, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def digest(docs: DataFrame, **options) -> DataFrame:
    """Learns from the documents that aren't held out and scores all; null texts are empty ones (only the end)."""
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    training = base.where(~held_out(F.col("doc_id")))
    counts = cut_table(count_tokens(training))
    vocabulary = build_vocabulary(counts)
    encoded = cut_table(encode(base, counts, vocabulary))
    return score(encoded, vocabulary, fit(encoded, vocabulary, **options))
