"""Encoders over ego batches.

A batch has x (entities), and one row per neighbour: whose (entity's row), kind (source), weight
(confidence), v (its features) and back (the mean features of the entities it is linked to, its own
neighbourhood one hop out).  Layer one makes hidden states of entities and neighbours; layer two joins
them.  Typed encoders have matrices per source; agnostic ones share one and see weight 1.
"""
from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np

from provgraph.learn import tape
from provgraph.learn.tape import Var, const

TYPED = ("aware", "unweighted", "relational", "metapath", "typed_attention")  # a matrix per source
SOURCES = 2  # crowd features, tile neighbours
HEADS = 2  # of the typed transformer


class Mates:
    """The entities of some whole tiles, each of which has all others of its tile for neighbours.

    They stand in slots, the first one of every tile (largest tiles first), then every second one, and so on, so sums over
    tiles are additions of whole stretches, and an entity's neighbours' sum is its tile's less itself: no row a pair.
    """

    def __init__(self, tile: np.ndarray, mask: np.ndarray, v: np.ndarray, back: np.ndarray):
        has = np.zeros(tile.max() + 1, bool)
        has[tile[mask]] = True
        kept = np.flatnonzero(has[tile])
        at = (np.cumsum(has) - 1)[tile[kept]]
        count = np.bincount(at)
        rank = np.empty(len(count), np.int64)
        rank[np.argsort(-count, kind="stable")] = np.arange(len(count))
        by = np.argsort(at, kind="stable")
        slot = np.empty(len(at), np.int64)
        slot[by] = np.arange(len(at)) - (np.cumsum(count) - count)[at[by]]
        order = np.lexsort((rank[at], slot))
        place = np.empty(len(tile), np.int64)
        place[kept[order]] = np.arange(len(order))
        self.sizes, self.own = np.bincount(slot), place[mask]
        self.v, self.back = v[kept[order]], back[kept[order]]
        self.rank, self.slot = rank[at][order], slot[order]
        self.degree = (count[at][order] - 1)[self.own]

    def _less_own(self, x: np.ndarray) -> np.ndarray:
        total, out, i = np.zeros((self.sizes[0], *x.shape[1:]), x.dtype), np.empty_like(x), 0
        for m in self.sizes:
            total[:m] += x[i : i + m]
            i += m
        i = 0
        for m in self.sizes:
            np.subtract(total[:m], x[i : i + m], out=out[i : i + m])
            i += m
        return out

    def sums(self, x: np.ndarray) -> np.ndarray:
        """For each row of the batch the sum over its neighbours."""
        return self._less_own(x).take(self.own, axis=0)

    def gathered(self, z: Var) -> Var:
        def back(g):
            full = np.zeros((len(z.value), g.shape[1]), g.dtype)
            full[self.own] = g
            return self._less_own(full)

        return Var(self.sums(z.value), ((z, back),))

    def pairs(self) -> tuple[np.ndarray, np.ndarray]:
        """(row of the batch, entity) of all neighbours, for what differs from one to the next."""
        rank, slot, i, whose, who = self.rank[self.own], self.slot[self.own], 0, [], []
        for j, m in enumerate(self.sizes):
            one = np.flatnonzero((rank < m) & (slot != j))
            whose.append(one)
            who.append(i + rank[one])
            i += m
        return np.concatenate(whose), np.concatenate(who)


@dataclass
class Batch:
    x: np.ndarray
    whose: np.ndarray
    kind: np.ndarray
    weight: np.ndarray
    v: np.ndarray
    back: np.ndarray
    keys: np.ndarray | None = None  # for masks that repeat whatever the partitioning
    kept: dict = field(default_factory=dict)  # what doesn't depend on weights, worked out once for all runs
    tile: np.ndarray | None = None  # each entity's tile, if its tile neighbours are no rows above but all others of the tile
    mine: np.ndarray | None = None  # an entity's v, as a neighbour
    mates: Mates | None = None

    def once(self, key, make):
        if key not in self.kept:
            self.kept[key] = make()
        return self.kept[key]


def shapes(model: str, d: int, dv: int, h: int, out: int) -> dict[str, tuple[int, int]]:
    p = {"self1": (d, h), "b1": (1, h), "head": (h, out), "hb": (1, out)}
    if model == "probe":
        return {"head": (d, out), "hb": (1, out)}
    if model == "mlp":
        return p | {"self2": (h, h), "b2": (1, h)}
    kinds = range(SOURCES) if model in TYPED else ["all"]
    p |= {"self2": (h, h), "b2": (1, h)}
    for s in kinds:
        # A metapath's neighbour is the entity at its far end, so what lies between has no matrix of its own.
        p |= {f"back_{s}": (d, h), f"nb_{s}": (1, h), f"n2_{s}": (h, h)} | ({f"in_{s}": (d, h)} if model == "metapath" else {f"n1_{s}": (dv, h), f"in_{s}": (dv, h)})
    if model == "attention":
        p |= {"att": (2 * h, 1)}
    if model == "typed_attention":
        p |= {"q": (h, h)} | {f"k_{s}": (h, h) for s in kinds} | {f"prior_{s}": (1, 1) for s in kinds}
    if model == "metapath":
        p |= {f"att_{s}": (2 * h, 1) for s in kinds} | {"sem": (h, h), "semq": (h, 1)}
    if model == "contrastive":
        p |= {"disc": (h, h)}
    return p


def link_shapes(scorer: str, d: int, dv: int, h: int) -> dict[str, tuple[int, int]]:
    """A feature's tower and, for ``bilinear``, the matrix between it and the entity's state."""
    p = {"f1": (dv, h), "nb_f": (1, h), "f2": (h, d)}
    return p | {"bil": (d, d)} if scorer == "bilinear" else p


def initial(model: str, d: int, dv: int, h: int, out: int, seed: int, scorer: str = "") -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    every = shapes(model, d, dv, h, out)
    if scorer:
        every |= link_shapes(scorer, d if model == "probe" else h, dv, h)
    return {k: np.zeros(s) if k.startswith(("b", "hb", "nb")) and k.split("_")[0] in ("b1", "b2", "hb", "nb") else rng.normal(0, (2 / (s[0] + s[1])) ** 0.5, s) for k, s in every.items()}


def dropout_mask(width: int, rate: float, keys: np.ndarray, salt: int, kind=np.float64) -> Var:
    with np.errstate(over="ignore"):
        u = keys.astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + (np.arange(width, dtype=np.uint64) + np.uint64(salt * 7919 + 1)) * np.uint64(0xC2B2AE3D27D4EB4F)
        u ^= u >> np.uint64(31)
        u *= np.uint64(0xBF58476D1CE4E5B9)
        u ^= u >> np.uint64(29)
    return const((((u >> np.uint64(11)).astype(np.float64) / (1 << 53) >= rate) / (1 - rate)).astype(kind))


def dropout(x: Var, rate: float, keys: np.ndarray | None, salt: int) -> Var:
    """Masks from a counter hash of (row key, unit, salt): the same after a retry or another partitioning."""
    return x if not rate or keys is None else x * dropout_mask(x.value.shape[1], rate, keys, salt)


def normalised(b: Batch, weight: np.ndarray, groups: np.ndarray | None = None) -> np.ndarray:
    """Weights that add up to one per entity (or per entity and source); zero sums stay zero, leaving the self term."""
    key = b.whose if groups is None else b.whose * SOURCES + groups
    s = np.bincount(key, weight, len(b.x) * (1 if groups is None else SOURCES))
    if b.mates is not None and groups is None:
        s += b.mates.degree
    return np.divide(weight, s[key], out=np.zeros(len(weight)), where=s[key] > 0)


def mates_share(b: Batch, weight: np.ndarray | None) -> np.ndarray:
    """The share of each tile neighbour, all of weight one, beside others of ``weight`` (None: by themselves)."""
    s = b.mates.degree + (0.0 if weight is None else np.bincount(b.whose, weight, len(b.x)))
    return np.divide(1.0, s, out=np.zeros(len(b.x)), where=b.mates.degree > 0)[:, None]


@dataclass
class Hood:
    """One source's neighbours (or all, for models that don't tell sources apart), as far as no weight changes it."""

    name: object
    whose: tape.Slots | None
    share: np.ndarray  # a column for the neighbours or, where an entity's have one share, for the entities
    by_entity: bool
    inputs: Var  # with a column of ones
    first: Var  # the first layer's input, summed per entity before any matrix
    mates: Mates | None = None
    pick: tuple | None = None  # which state each neighbour has, where several share one

    def paired(self, n: int) -> Hood:
        """With a row a neighbour, for what differs from one to the next."""
        if self.mates is not None and self.pick is None:
            whose, who = self.mates.pairs()
            self.whose = tape.Slots(whose, n)
            who = who[self.whose.order]
            self.pick = who, tape.Slots(who, len(self.mates.v))
        return self

    def each(self, z: Var) -> Var:
        """A row a neighbour from a row a state."""
        return z if self.pick is None else tape.spread(z, *self.pick)

    def gathered(self, z: Var, n: int) -> Var:
        """The entities' sums of their neighbours' states by share."""
        if self.mates is not None:
            return self.mates.gathered(z) * self.share
        return tape.segments(z, self.whose, n) * self.share if self.by_entity else tape.segments(z, self.whose, n, self.share)


def neighbourhood(model: str, b: Batch) -> list[Hood]:
    typed, path, n, f = model in TYPED, model == "metapath", len(b.x), b.x.dtype
    weighting = "aware" if model == "aware" else "source" if model in ("relational", "metapath") else "unit"

    def hood(s, at, w):
        whose = tape.Slots(b.whose[at], n)
        at = at[whose.order]
        share, v, mean = w[at][:, None].astype(f), (b.back if path else b.v)[at], np.zeros((n, 1), f)
        mean[whose.at] = share
        same = bool((mean[whose.at] == share).all())
        inputs = [b.back[at], np.ones((len(at), 1), f)] if path else [b.back[at], b.v[at], np.ones((len(at), 1), f)]
        return Hood(s, whose, mean if same else share, same, const(np.hstack(inputs)), const(tape.reduced(np.add, v * share, whose, n)))

    def tile(s, share):
        m, one = b.mates, np.ones((len(b.mates.v), 1), f)
        inputs = [m.back, one] if path else [m.back, m.v, one]
        return Hood(s, None, share.astype(f), True, const(np.hstack(inputs)), const(m.sums(m.back if path else m.v) * share.astype(f)), m)

    def make():
        if b.mates is not None:  # a crowd feature's edges as rows, the tile's entities by sums
            weight = {"aware": b.weight, "unit": np.ones(len(b.kind)), "source": None}[weighting]
            w = normalised(b, np.ones(len(b.kind)) if weight is None else weight, b.kind if weight is None else None)
            names = range(SOURCES) if typed else ["all", "all"]
            return [hood(names[0], np.arange(len(b.kind)), w), tile(names[1], mates_share(b, weight))]
        w = normalised(b, b.weight) if weighting == "aware" else normalised(b, np.ones(len(b.kind)), b.kind if weighting == "source" else None)
        return [hood(s, np.flatnonzero(b.kind == s), w) for s in range(SOURCES)] if typed else [hood("all", np.arange(len(b.kind)), w)]

    return b.once((weighting, typed, path), make)


def neighbour_terms(model: str, p: dict[str, Var], b: Batch) -> tuple[list[Var], list[Var]]:
    """What neighbours add to the first layer, and their own states; neither depends on the entity's x."""
    hoods = neighbourhood(model, b)
    d = b.back.shape[1]  # features that only some views have are no neighbour's
    far = lambda w: w if len(w.value) == d else tape.cut_rows(w, 0, d)
    parts = lambda s: [far(p[f"back_{s}"]), p[f"nb_{s}"]] if model == "metapath" else [far(p[f"back_{s}"]), p[f"n1_{s}"], p[f"nb_{s}"]]
    into = lambda w: far(w) if model == "metapath" else w
    return [h.first @ into(p[f"in_{h.name}"]) for h in hoods], [tape.relu(h.inputs @ tape.stack(parts(h.name))) for h in hoods]


def neighbour_sums(p: dict[str, Var], hoods: list[Hood], states: list[Var], n: int) -> Var:
    """What neighbours add to the second layer of models with constant shares: summed before the matrix, for they are linear."""
    out = None
    for d, z in zip(hoods, states):
        g = d.gathered(z, n) @ p[f"n2_{d.name}"]
        out = g if out is None else out + g
    return out


def hidden(model: str, p: dict[str, Var], b: Batch, rate: float = 0.0, salt: int = 0, terms: tuple | None = None, sums: Var | None = None) -> Var:
    """The entities' states before the head; ``terms`` and ``sums``: the neighbours' parts, if they are known."""
    x, n = const(b.x), len(b.x)

    def drop(v, k):
        if not rate or b.keys is None:
            return v
        return v * b.once((rate, salt * 4 + k, v.value.shape[1]), lambda: dropout_mask(v.value.shape[1], rate, b.keys, salt * 4 + k, v.value.dtype))

    if model == "probe":
        return x
    own = x @ p["self1"] + p["b1"]
    if model == "mlp":
        return drop(tape.relu(drop(tape.relu(own), 0) @ p["self2"] + p["b2"]), 1)
    path = model == "metapath"
    hoods, (added, states) = neighbourhood(model, b), terms or neighbour_terms(model, p, b)
    first = own
    for a in added:
        first = first + a
    h = drop(tape.relu(first), 0)
    second, paths = h @ p["self2"] + p["b2"], []
    if model in ("attention", "metapath", "typed_attention"):
        hoods = [d.paired(n) for d in hoods]
    if model == "typed_attention":
        asked, size = h @ p["q"], h.value.shape[1]
        keys = [(tape.rows(asked, d.whose) * d.each(z @ p[f"k_{d.name}"]), d.each(z @ p[f"n2_{d.name}"])) for d, z in zip(hoods, states)]
        for head in range(HEADS):
            mine = (np.arange(size) * HEADS // size == head)[None, :].astype(x.value.dtype)
            scores = [(k @ const(mine.T)) * (1 / (size / HEADS) ** 0.5) + p[f"prior_{d.name}"] for (k, _), d in zip(keys, hoods)]
            for d, (_, message), alpha in zip(hoods, keys, tape.softmax_over(scores, [d.whose for d in hoods], n)):
                second = second + tape.segments(message * alpha, d.whose, n) * mine
        return drop(tape.relu(second), 1)
    if model in ("attention", "metapath"):
        scores, messages = [], []
        for d, z in zip(hoods, states):
            message = z @ p[f"n2_{d.name}"]
            a = p["att"] if model == "attention" else p[f"att_{d.name}"]
            half = len(a.value) // 2
            scores.append(tape.relu(tape.rows(h @ tape.cut_rows(a, 0, half), d.whose) + d.each(message @ tape.cut_rows(a, half, 2 * half)), 0.2))
            messages.append(d.each(message))
        whose = [d.whose for d in hoods]
        alphas = [tape.softmax_by(s, w, n) for s, w in zip(scores, whose)] if path else tape.softmax_over(scores, whose, n)
        for message, alpha, w in zip(messages, alphas, whose):
            gathered = tape.segments(message * alpha, w, n)
            if path:
                paths.append(gathered)
            else:
                second = second + gathered
    else:
        second = second + (sums or neighbour_sums(p, hoods, states, n))
    if path:
        votes = [tape.row_sum(tape.tanh(g @ p["sem"]) @ p["semq"]) for g in paths]
        means = [tape.total(v) * (1 / max(1, n)) for v in votes]
        es = [tape.exp(m) for m in means]
        z = tape.reciprocal(es[0] + es[1])
        for g, e in zip(paths, es):
            second = second + g * (e * z)
    return drop(tape.relu(second), 1)


def outputs(model: str, p: dict[str, Var], b: Batch, rate: float = 0.0, salt: int = 0) -> Var:
    return hidden("mean_pool" if model == "contrastive" else model, p, b, rate, salt) @ p["head"] + p["hb"]


def link_scores(p: dict[str, Var], states: Var, whose: np.ndarray, v: np.ndarray) -> Var:
    """A score per pair: the entity's state times the feature's, through a matrix for the bilinear scorer."""
    f = tape.relu(const(v) @ p["f1"] + p["nb_f"]) @ p["f2"]
    own = tape.rows(states, whose)
    return tape.row_sum((own @ p["bil"] if "bil" in p else own) * f) * (1 / states.value.shape[1] ** 0.5)


def contrast_loss(p: dict[str, Var], b: Batch) -> Var:
    """Tells real states from those of features shuffled among the batch's entities, against the batch's mean readout."""
    order = np.argsort((b.keys if b.keys is not None else np.arange(len(b.x))) * 2654435761 % 2**32, kind="stable")
    fake = replace(b, x=b.x[np.roll(order, 1)[np.argsort(order)]])
    terms = neighbour_terms("mean_pool", p, b)  # the same for both
    sums = neighbour_sums(p, neighbourhood("mean_pool", b), terms[1], len(b.x))
    real, false = (hidden("mean_pool", p, each, terms=terms, sums=sums) for each in (b, fake))
    mean = tape.segments(real, np.zeros(len(b.x), np.int64), 1) * (1 / max(1, len(b.x)))
    summary = tape.reciprocal(tape.exp(mean * -1.0) + 1.0)
    disc = tape.row_sum(p["disc"] * summary)
    score = lambda h: h @ disc
    return tape.logistic(score(real), np.ones(len(b.x))) + tape.logistic(score(false), np.zeros(len(b.x)))
