"""The training-data operators against brute force, on small tables with awkward rows."""
import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from provgraph.llm import bloom, decontamination, fm_index, forest, hilbert, language_model, licenses, line_dedup, near_duplicates, pfair, substring_dedup, toxicity, words

LOWER = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})
ALNUM = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
BLANK = re.compile("[^\x20\x09-\x0d]+")
KINDS = "doc_id long, text string, lang string, source string, n_chars long"
sha = lambda s: hashlib.sha256(s.encode()).hexdigest()


def awkward(seed=1, n=60):
    r = random.Random(seed)
    vocab = [f"w{i}" for i in range(40)] + ["Été", "naïve", "日本", "x-y", "MIT", "license", "Licence", "gpl"]
    text = lambda k: "".join(r.choice(vocab) + r.choice([" ", "  ", "\n", "\t", ". ", " "]) for _ in range(k))
    shared, passage = text(70), " ".join(r.choice(vocab) for _ in range(120))
    texts = [None, "", " \n\t ", "one", "Été", shared, shared, shared.upper(), "a b", "a b"] + [text(r.choice([2, 9, 30, 200])) for _ in range(n)]
    texts += [f"{text(5)} {passage} {text(7)}" for _ in range(4)] + [passage[: len(passage) // 2], shared + " tail", text(9000)]
    rows = [(i, t, r.choice(["en", "de", None]), r.choice(["s0", "s0", "s1", "s2", None]), None if t is None else len(t)) for i, t in enumerate(texts)]
    r.shuffle(rows)
    return rows + [(None, shared, None, None, None)]


@pytest.fixture(scope="module")
def rows():
    return awkward()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, KINDS).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], KINDS)


def test_words_and_blocks():
    texts = [None, b"", b"A b  c", "ÉTÉ\x85x y".encode(), b"Q" * 100]
    for table, rule, low in ((words.BLANK, BLANK, False), (words.ALNUM_LOWER, ALNUM, True)):
        for size in (1, 5, 1 << 20):
            got = [[b.word(i).decode() for i in range(b.first[d], b.first[d + 1])] for lo, hi, b in words.blocks(texts, table, size) for d in range(hi - lo)]
            assert got == [rule.findall((t or b"").decode().translate(LOWER) if low else (t or b"").decode()) for t in texts]
    b = words.Block([b"ab abc ab", b"abc"], words.BLANK)
    h = b.hashes()
    assert h[0] == h[2] != h[1] == h[3]


def test_bloom_never_misses(spark):
    import pandas as pd

    keys = np.random.default_rng(0).integers(0, 2**63, 4000)
    again = keys[:900]
    df = spark.createDataFrame(pd.DataFrame({"k": np.concatenate([keys, again])})).repartition(5)
    twice = bloom.twice_filter(df, lambda b: iter([b.column("k").to_numpy().view(np.uint64)]), 21)
    assert bloom.member(twice, again.view(np.uint64), 21).all()
    assert bloom.member(twice, keys[900:].view(np.uint64), 21).mean() < 0.02


# --- sharding -----------------------------------------------------------------------------------


@pytest.mark.parametrize("dims,bits", [(2, 4), (3, 3)])
def test_curve_is_a_hilbert_curve(spark, dims, bits):
    df = spark.range(1 << dims * bits).select(*[F.expr(f"shiftright(id, {bits * i}) & {(1 << bits) - 1}").alias(f"a{i}") for i in range(dims)])
    got = sorted((r["curve"], [r[f"a{i}"] for i in range(dims)]) for r in hilbert.with_curve(df, [F.col(f"a{i}") for i in range(dims)], bits).collect())
    assert [c for c, _ in got] == list(range(len(got)))
    assert all(sum(abs(x - y) for x, y in zip(p[1], q[1])) == 1 for p, q in zip(got, got[1:]))


@pytest.mark.parametrize("law", ["rows", "bytes"])
def test_shards(docs, rows, law):
    got = hilbert.digest(docs, law=law).collect()
    text = {r[0]: r[1] for r in rows}
    assert len(got) == len(rows)
    assert all(r["size"] == len((text[r["doc_id"]] or "").encode()) + 8 and r["text_crc32"] == zlib.crc32((text[r["doc_id"]] or "").encode()) for r in got)
    by = defaultdict(list)
    for r in got:
        by[r["shard"]].append(r)
    assert all(sorted(r["slot"] for r in v) == list(range(len(v))) for v in by.values()) and set(by) <= set(range(24))
    if law == "rows":
        sizes = [len(by[s]) for s in range(24)]
        assert max(sizes) - min(sizes) <= 1
    curve = [r["curve"] for s in sorted(by) for r in sorted(by[s], key=lambda r: r["slot"])]
    assert curve == sorted(curve)


def test_shards_empty(empty):
    assert hilbert.digest(empty).count() == 0


def test_sharding_prunes(spark, sf, tmp_path):
    d = spark.read.parquet(f"{sf}/documents.parquet").drop("text")
    s = hilbert.shard(d, ["source", "lang", "n_chars"], shards=8)
    hilbert.write_shards(s, str(tmp_path / "x"))
    assert spark.read.parquet(str(tmp_path / "x")).count() == d.count()
    spread = hilbert.manifest(s, ["n_chars"]).agg(F.avg(F.col("max_n_chars") - F.col("min_n_chars"))).first()[0]
    assert spread < d.agg(F.max("n_chars") - F.min("n_chars")).first()[0]


# --- decontamination ----------------------------------------------------------------------------


def brute_hits(rows, bench, n=10):
    grams = defaultdict(set)
    for i, t in bench:
        w = ALNUM.findall((t or "").translate(LOWER))
        for k in range(max(1, len(w) - n + 1) if w else 0):
            grams[tuple(w[k : k + n])].add(str(i))
    out = {}
    for r in rows:
        w = ALNUM.findall((r[1] or "").translate(LOWER))
        hit, items = set(), set()
        for size in {len(g) for g in grams}:
            for k in range(len(w) - size + 1):
                if got := grams.get(tuple(w[k : k + size])):
                    hit |= set(range(k, k + size))
                    items |= got
        out[r[0]] = (len(w), len(hit), len(items), sha(",".join(sorted(items))), bool(hit))
    return out


@pytest.mark.parametrize("part", [1 << 20, 40])
def test_decontamination(spark, docs, rows, part):
    long = next(r[1] for r in rows if r[1] and len(r[1].split()) > 100)
    bench = [(1, " ".join(long.split()[5:30])), (2, "one"), (3, None), (4, ""), (10, "W3 w4!"), (12, "never seen words here at all in any of those texts"), (1, "été")]
    got = {r["doc_id"]: tuple(r)[1:] for r in decontamination.digest(docs, spark.createDataFrame(bench, "item_id long, text string"), max_part_bytes=part).collect()}
    assert got == brute_hits(rows, bench)


def test_decontamination_modes(spark, docs):
    bench = spark.createDataFrame([(1, "one")], "item_id long, text string")
    assert decontamination.decontaminate(docs, bench).where("text = 'one'").count() == 0
    cut = decontamination.decontaminate(docs, bench, mode="spans")
    assert cut.columns == docs.columns and cut.count() == docs.count() and cut.where("doc_id = 3").first()["text"] == ""
    assert decontamination.decontaminate(docs, bench.limit(0)).count() == docs.count()


# --- near duplicates ----------------------------------------------------------------------------


def brute_components(rows, n):
    sets = {}
    for i, (d, t, *_) in enumerate(rows):
        w = BLANK.findall((t or "").translate(LOWER))
        sets[i] = {tuple(w)} if 0 < len(w) < n else {tuple(w[k : k + n]) for k in range(len(w) - n + 1)}
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            k = len(sets[a] & sets[b])
            if k and 100 * k >= 80 * len(sets[a] | sets[b]):
                parent[find(a)] = find(b)
    ids = defaultdict(list)
    for i, r in enumerate(rows):
        ids[find(i)].append(r[0])
    return {r[0]: (len(sets[i]), min((x for x in ids[find(i)] if x is not None), default=None)) for i, r in enumerate(rows)}


@pytest.mark.parametrize("n", [2, 5])
def test_near_duplicates(spark, n):
    rows = awkward(7)
    r = random.Random(9)
    base = [f"v{r.randrange(5000)}" for _ in range(400)]
    for k in range(120):  # copies with changed words, many near the threshold
        w = list(base)
        for _ in range(r.randrange(0, 26)):
            w[r.randrange(len(w))] = f"u{r.randrange(9999)}"
        rows.append((1000 + k, " ".join(w), "en", "s1", 1))
    got = near_duplicates.near_duplicates(spark.createDataFrame(rows, KINDS).repartition(4), shingle=n).collect()
    want = brute_components(rows, n)
    assert {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in got} == want
    assert all(x["kept"] == (x["doc_id"] == x["component_id"]) for x in got)


def test_near_duplicates_empty_and_keep_one(empty, docs):
    assert near_duplicates.near_duplicates(empty).count() == 0
    kept = near_duplicates.keep_one(docs)
    assert kept.columns == docs.columns and kept.where("text is null").count() == 1


def test_chunks_meet_under_the_threshold():
    r = np.random.default_rng(2)
    for _ in range(300):
        a = r.integers(0, 1 << 16, near_duplicates.SIZE, dtype=np.uint16)
        b = a.copy()
        at = r.choice(near_duplicates.SIZE, near_duplicates.CHUNKS * (near_duplicates.ERRORS + 1) - 1, replace=False)
        b[at] += 1
        assert any((a[k] == b[k]).all() for _, k in near_duplicates._KEPT)


# --- licenses -----------------------------------------------------------------------------------


def test_license_base_columns(docs, rows):
    phrases = {tuple(p.split()): label for p, label in licenses.BASE.items()}
    extra = {r["doc_id"]: r for r in licenses.digest(docs).collect()}
    for d, t, *_ in rows:
        w = ALNUM.findall((t or "").translate(LOWER))
        at = sorted((i, label) for p, label in phrases.items() for i in range(len(w)) if tuple(w[i : i + len(p)]) == p)
        r = extra[d]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == (len(w), len(at), at[0][0] if at else None, at[-1][0] if at else None, ",".join(sorted({x for _, x in at})))
        assert 0 <= r["score"] <= 1 and set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))


def test_license_rules_and_suppression(spark):
    texts = ["SPDX-License-Identifier: GPL-3.0-or-later", "Licensed under the Apache License, Version 2.0 (the", "under the MIT-License. the mit license", "GNU Lesser General Public License v2.1", "no terms here", "BSD 3-Clause License", "-- leading mit license", None]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: (r["labels"], r["n_base"], r["first_word"]) for r in licenses.digest(df).collect()}
    assert got[0][0] == "gpl-3.0" and got[1] == ("apache,apache-2.0", 1, 3) and got[2][:2] == ("mit", 2) and got[4] == ("", 0, None) and got[6][1:] == (1, 1)
    assert "lgpl-2.1" in got[3][0] and "gpl" in got[3][0] and got[5][0] == "bsd-3-clause"
    found = licenses.detect(df).where("doc_id = 1").first()["detections"]
    assert len({(x["s"], x["e"]) for x in found}) == len(found)
    assert len(licenses.rules()) > 250 and all(re.compile(r.pattern) for r in licenses.rules())


def _spelled(parsed, r):
    """Texts of a parsed pattern: each alternative at least once, optional parts absent and present."""
    from re import _constants as c

    out = [""]
    for op, arg in parsed:
        if op is c.LITERAL:
            more = [chr(arg)]
        elif op is c.IN:
            more = [chr(arg[0][1] if arg[0][0] is c.LITERAL else arg[0][1][0])]
        elif op is c.SUBPATTERN:
            more = _spelled(arg[-1], r)
        elif op is c.BRANCH:
            more = [x for a in arg[1] for x in _spelled(a, r)]
        elif op is c.MAX_REPEAT:
            more = ([""] if arg[0] == 0 else []) + _spelled(arg[2], r)
        else:
            more = [""]
        r.shuffle(out)
        out = [x + y for x in out for y in more] if len(out) * len(more) <= 60 else [out[i % len(out)] + more[i % len(more)] for i in range(max(len(out), len(more)))]
    return out


def test_license_gates_lose_nothing(spark):
    from re._parser import parse

    r, rules = random.Random(2), licenses.rules()
    for rule in rules:
        for t in _spelled(parse(rule.pattern), r):
            norm = f" {t} "
            assert re.search(rule.pattern, norm) and any(k in norm for k in rule.keywords) and any(g in norm for g in rule.gate), (rule, t)
    texts = ["GPLv2", "gnu gpl v2", "Apache 2.0", "LGPL 2.1", "ASL 2", "simplified BSD license", "FreeBSD license", "original BSD license", "zero clause BSD license", "Berkeley Software Distribution license", "internet systems consortium license", "creative commons attribution noderivs license", "none"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got, want = ([x["detections"] for x in licenses.detect(df, gated=g).orderBy("doc_id").collect()] for g in (True, False))
    assert got == want and all(got[:-1]) and not got[-1]


# --- nearest neighbours -------------------------------------------------------------------------


def test_neighbours(spark):
    r = np.random.default_rng(4)
    x = r.normal(size=(900, 16)).astype(np.float32)
    x[3] = 0
    x[5] = x[6]
    rows = [(i, v.tolist(), i) for i, v in enumerate(x)] + [(2000, None, 1), (2020, [float("nan")] * 16, 1), (None, x[0].tolist(), 2), (2040, [1.0], 3)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = defaultdict(list)
    for q in forest.neighbours(df).orderBy("query_id", "rank").collect():
        got[q["query_id"]].append((q["vec_id"], q["score"]))
    x = x.astype(float)
    hits = total = 0
    for q in range(0, 900, 20):
        order = sorted((i for i in range(900) if i not in (q, 3)), key=lambda i: (-(x[i] @ x[q]), i))[:20]
        assert [s for _, s in got[q]] == sorted((s for _, s in got[q]), reverse=True) and len(got[q]) == 20
        assert all(abs(x[i] @ x[q] - s) < 1e-9 for i, s in got[q])
        hits += len({i for i, _ in got[q]} & set(order))
        total += 20
    assert hits / total >= 0.9 and set(got) == set(range(0, 900, 20))
    assert forest.neighbours(df.limit(0)).count() == 0


def test_forest_searches_part_of_the_leaves(spark):
    """One rule at every size: the small table too is searched by the registered share, without losing neighbours."""
    x = np.random.default_rng(6).normal(size=(900, 16))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = defaultdict(set)
    for q in forest.neighbours(df, leaf=32).collect():
        got[q["query_id"]].add(q["vec_id"])
    hits = sum(len(got[q] & set(sorted((i for i in range(900) if i != q), key=lambda i: -(x[i] @ x[q]))[:20])) for q in range(0, 900, 20))
    assert hits >= 0.95 * 900
    # A tenth of the rows can't hold all neighbours: the share is obeyed below any number of rows.
    few = {(r["query_id"], r["vec_id"]) for r in forest.neighbours(df, leaf=32, share=0.1).collect()}
    assert len(few & {(q, i) for q, a in got.items() for i in a}) < 0.9 * 900


def test_forest_on_clusters(spark):
    """Over 20,000 rows in clusters, the registered settings: recall against brute force."""
    r = np.random.default_rng(8)
    centres = r.normal(size=(300, 32))
    x = centres[r.integers(0, 300, 21_000)] + 0.3 * r.normal(size=(21_000, 32))
    import pandas as pd

    df = spark.createDataFrame(pd.DataFrame({"vec_id": np.arange(len(x)), "embedding": x.tolist()})).repartition(4)
    got = defaultdict(set)
    for q in forest.neighbours(df, every=700).collect():
        got[q["query_id"]].add(q["vec_id"])
    hits = sum(len(got[q] & set(np.argsort(-np.where(np.arange(len(x)) == q, -np.inf, x @ x[q]))[:20].tolist())) for q in range(0, len(x), 700))
    assert set(got) == set(range(0, len(x), 700)) and hits >= 0.9 * 20 * len(got)


# --- language model -----------------------------------------------------------------------------


def test_network_gradients():
    net = language_model.Network(4, 3)
    net.p = {k: v.astype(np.float64) + (0.1 if k in "CW" else 0) for k, v in net.p.items()}
    r = np.random.default_rng(0)
    cls = r.integers(0, language_model.CLASSES, (6, 3))
    item = np.where(cls < language_model.HEAD_CLASSES, r.integers(0, language_model.HEAD_SIZE, cls.shape), 0)
    live = np.ones(cls.shape, bool)
    live[4:, 1] = False
    x, h = net.symbol(cls, item), r.normal(size=(3, 4))
    new = np.zeros(cls.shape, bool)
    new[3, 0] = new[0, 2] = True
    loss, _, grad, _ = net.gradients(x, cls, item, live, h, new)
    for k in net.p:
        spots = np.argwhere(grad[k] != 0)
        for i in map(tuple, spots[r.permutation(len(spots))[:3]]):
            old = net.p[k][i]
            both = []
            for d in (1e-5, -1e-5):
                net.p[k][i] = old + d
                both.append(net.gradients(x, cls, item, live, h, new)[0])
            net.p[k][i] = old
            assert abs((both[0] - both[1]) / 2e-5 - grad[k][i]) < 1e-3 * max(1, abs(grad[k][i])), k


def test_state_runs_through_whole_documents():
    net = language_model.Network(4, 3)
    r = np.random.default_rng(1)
    docs = [(c := r.integers(0, language_model.CLASSES, n), np.where(c < language_model.HEAD_CLASSES, 1, 0)) for n in (1, 70, 5, 200)]
    for (c, i), got in zip(docs, net.log_likelihood(docs)):
        h, total = np.zeros((1, 4), np.float32), 0.0
        for a, b in zip(c, i):
            total += net.outputs(h, np.array([a]), np.array([b]))[0]
            h = net.step(net.symbol(np.array([a]), np.array([b])), h)[0]
        assert abs(total - got) < 1e-2


def test_scores(spark, rows, docs):
    got = {r["doc_id"]: r for r in language_model.digest(docs).collect()}
    tokens = {r[0]: BLANK.findall((r[1] or "").translate(LOWER)) + ["\n"] for r in rows}
    out = {d: zlib.crc32(("" if d is None else str(d)).encode()) % 7 == 2 for d in tokens}
    c = Counter(t for d, ts in tokens.items() if not out[d] for t in ts)
    n, v = sum(c.values()), len(c)
    for d, ts in tokens.items():
        r = got[d]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (out[d], len(ts), sum(t in c for t in ts), n)
        assert abs(r["base_score"] - sum(math.log10((c[t] + 1) / (n + v + 1)) for t in ts)) < 1e-6 and math.isfinite(r["score"]) and r["score"] <= 0


def test_network_learns_from_every_document(spark):
    """What only documents late in hash order hold is learnt, however long an early one is."""
    ids = spark.range(1900).where(~language_model.held_out(F.col("id"))).orderBy(F.xxhash64("id"), "id").toPandas()["id"].tolist()
    rows = [(i, " ".join(["a", "b"] * 4)) for i in ids[1:1500]] + [(i, " ".join(["c", "d", "e"] * 30)) for i in ids[1500:]] + [(ids[0], "a b " * 210_000)]
    tests = [i for i in range(5000, 5200) if zlib.crc32(str(i).encode()) % 7 == 2]
    rows += [(i, " ".join(["c", "d", "e"] * 30)) for i in tests]
    got = [r for r in language_model.digest(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect() if r["doc_id"] in tests]
    assert len(got) == len(tests) > 10 and min(r["score"] / r["n_tokens"] for r in got) > -0.2


def test_probabilities_add_up():
    """Over a whole vocabulary and the unseen word, the model's probabilities sum to one."""
    counts = {i + 1: n for i, n in enumerate([900, 500, 300] + [40] * 600 + [3] * 200 + [1] * 300)}
    import pandas as pd

    h = np.array(list(counts), np.int64)
    head = sorted(counts.items(), key=lambda kv: (-kv[1], kv[0]))[: language_model.HEAD_CLASSES * language_model.HEAD_SIZE]
    tail = pd.Series(counts).drop([k for k, _ in head])
    mass = np.ones(language_model.TAIL_CLASSES)
    edges = np.array([-40, -3], np.int64)
    for k, g in enumerate((40, 3, 1)):
        mass[k] = (tail[tail == g] + 1).sum()
    vocabulary = language_model.Vocabulary(head, edges, mass, len(counts), sum(counts.values()))
    net = language_model.Network(4, 3)
    h = np.append(h, 10**9).view(np.uint64)
    cls, item, share = vocabulary.place(h, np.append(list(counts.values()), 0))
    lp = net.outputs(np.repeat(np.random.default_rng(0).normal(size=(1, 4)), len(h), 0).astype(np.float32), cls, item) / np.log(10) + share
    used = set(cls.tolist())
    empty_classes = [c for c in range(language_model.CLASSES) if c not in used]
    assert abs((10**lp).sum() + len(empty_classes) / language_model.CLASSES - 1) < 0.02


# --- lines and substrings -----------------------------------------------------------------------


def test_lines(spark):
    r = random.Random(2)
    pool = ["Shared Line Here", " shared line here\t", "short", "ÉÉÉÉÉÉÉÉÉÉ", "ééééééééé", "unique " + "x" * 30, ""]
    rows = [(i, None if i == 3 else "\n".join(r.choice(pool) + (str(r.randrange(4)) if r.random() < 0.3 else "") for _ in range(r.randrange(0, 9)))) for i in range(40)] + [(None, "shared line here")]
    got = {x["doc_id"]: tuple(x)[1:] for x in line_dedup.digest(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), bits=18 + 3).collect()}
    key = lambda s: s.strip(" \t\n\v\f\r").translate(LOWER)
    held = defaultdict(set)
    for d, t in rows:
        if d is not None:
            for s in (t or "").split("\n"):
                held[key(s)].add(d)
    for d, t in rows:
        lines = (t or "").split("\n")
        keep = [s for s in lines if d is None or len(key(s)) < 10 or len(held[key(s)]) < 2 or min(held[key(s)]) == d]
        assert got[d] == (len(lines), len(lines) - len(keep), sha("\n".join(keep)))
    assert line_dedup.digest(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def brute_removed(rows, window):
    first = {}
    split = {i: (r[0], BLANK.findall(r[1] or "")) for i, r in enumerate(rows)}
    for d, w in split.values():
        for i in range(len(w) - window + 1 if d is not None else 0):
            g = tuple(w[i : i + window])
            first[g] = min(first.get(g, d), d)
    out = {}
    for d, w in split.values():
        gone = {k for i in range(len(w) - window + 1 if d is not None else 0) if first[tuple(w[i : i + window])] < d for k in range(i, i + window)}
        out[d] = (len(w), len(gone), sha(" ".join(x for i, x in enumerate(w) if i not in gone)))
    return out


@pytest.mark.parametrize("options", [{}, {"window": 6, "seed": 3, "hot": 5, "shard_bytes": 3000}])
def test_substrings(docs, rows, options):
    got = {x["doc_id"]: tuple(x)[1:] for x in substring_dedup.digest(docs, bits=21, **options).collect()}
    assert got == brute_removed(rows, options.get("window", 50))


def test_substrings_empty(empty):
    assert substring_dedup.digest(empty, bits=21).count() == 0


def test_matching_statistics():
    r = np.random.default_rng(3)
    for _ in range(20):
        texts = [r.integers(1, 4, r.integers(1, 30)) for _ in range(8)]
        index = fm_index.FMIndex(texts, np.arange(8)[::-1].copy(), 7)
        asked = [r.integers(0, 6, r.integers(1, 25)) for _ in range(6)] + texts[:2]
        for q, (length, owner) in zip(asked, index.matching_statistics(asked)):
            for i in range(len(q)):
                n, who = 0, -1
                for k in range(1, min(7, len(q) - i) + 1):
                    hits = [7 - t for t, x in enumerate(texts) if any((x[j : j + k] == q[i : i + k]).all() for j in range(len(x) - k + 1))]
                    if not hits:
                        break
                    n, who = k, min(hits)
                assert (length[i], owner[i]) == (n, who)


# --- mixing and toxicity ------------------------------------------------------------------------


def test_periods_keep_the_weights():
    r = random.Random(1)
    cases = [{f"s{i}": r.randrange(1, 60) for i in range(r.randrange(1, 9))} for _ in range(20)]
    cases += [pfair.whole_weights({"a": 0.7, "b": 0.2999, "c": 0.0001}), pfair.whole_weights({f"s{i}": 1 if i else 30 for i in range(600)})]
    for shares in cases:
        size, got = sum(shares.values()), Counter()
        order = sorted((t, s) for s, ts in pfair.period(shares).items() for t in ts)
        assert [t for t, _ in order] == list(range(size))
        for t in range(1, size + 1):
            s = order[t - 1][1]
            got[s] += 1
            assert abs(got[s] * size - shares[s] * t) < size
        assert got == Counter(shares)
        due = {s: [-(-(j + 1) * size // a) for j in range(a)] for s, a in shares.items()}
        assert all(j * size // shares[s] <= t < d for s, ts in pfair.period(shares).items() for j, (t, d) in enumerate(zip(ts, due[s])))


def test_weights_are_exact():
    assert pfair.whole_weights({"a": 0.7, "b": 0.2999, "c": 0.0001}) == {"a": 7000, "b": 2999, "c": 1}
    assert pfair.whole_weights({"a": "0.5", "b": 1}) == {"a": 1, "b": 2}
    for bad in ({"a": 0, "b": 1}, {"a": 0.123456789, "b": 0.3}):
        with pytest.raises(ValueError):
            pfair.whole_weights(bad)


def test_mix(docs, rows, empty):
    got = pfair.mix(docs, {"s0": 1, "s1": 3, "s2": 1}, block_rows=4).collect()
    assert sorted(x["doc_id"] if x["doc_id"] is not None else -1 for x in got) == sorted(r[0] if r[0] is not None else -1 for r in rows)
    assert all(x["release"] <= x["slot"] < x["deadline"] for x in got)
    assert len({(x["slot"], x["pos"]) for x in got}) == len(got)
    assert pfair.mixed(docs).columns == docs.columns and pfair.mix(empty).count() == 0 and pfair.mixed(empty).count() == 0


def test_many_blocks_stay_near_their_targets(spark):
    """100,000 blocks and more: while all sources have rows, each stays less than one block from its exact target."""
    rows = spark.range(120_000).selectExpr("id", "case when id % 1000 = 0 then 'c' when id % 10 < 7 then 'a' else 'b' end source")
    got = pfair.mix(rows, {"a": 0.7, "b": 0.2999, "c": 0.0001}, block_rows=1).orderBy("slot").select("source", "slot").collect()
    last = min(max(r["slot"] for r in got if r["source"] == s) for s in "ab")
    n = Counter()
    for r in got:
        if r["slot"] > last:
            break
        n[r["source"]] += 1
        assert abs(n[r["source"]] * 10_000 - {"a": 7000, "b": 2999, "c": 1}[r["source"]] * (r["slot"] + 1)) < 10_000
    assert n["a"] > 80_000


def test_many_sources_keep_their_own_weights(spark):
    rows = spark.range(40_000).selectExpr("id", "concat('s', case when id % 2 = 0 then 0 else id % 1300 end) source")
    got = pfair.mix(rows, {"s0": 600}, other=1, block_rows=2)
    assert got.groupBy("slot").agg(F.countDistinct("source").alias("n")).where("n > 1").isEmpty()
    assert got.where("slot < release or slot >= deadline").isEmpty() and got.count() == 40_000 and got.select("source").distinct().count() > 600


def test_non_negative_risk():
    r = np.random.default_rng(0)
    x = np.vstack([r.normal(2, 1, (300, 5)), r.normal(-1, 1, (1200, 5)), r.normal(2, 1, (300, 5))]).astype(np.float32)
    w, b = toxicity.nnpu(x[:300], x[300:], 0.2)
    z = x @ w + b
    assert (z[1500:] > 0).mean() > 0.85 and (z[300:1500] > 0).mean() < 0.1


def test_toxicity(spark):
    r = random.Random(3)
    clean = [f"c{i}" for i in range(200)]
    rows, labels = [], []
    for i in range(700):
        bad = r.random() < 0.2
        w = [r.choice(clean) for _ in range(40)] + ([r.choice(["vile", "vilest", "grimword"]) for _ in range(3)] if bad else [])
        r.shuffle(w)
        rows.append((i, " ".join(w)))
        if r.random() < 0.6:
            labels.append((i, 1, int(bad)))
    rows += [(900, None), (901, ""), (None, "vile vile grimword")]
    df, lab = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = {x["doc_id"]: x for x in toxicity.digest(df, lab).collect()}
    assert all(x["held_out"] == (zlib.crc32(("" if d is None else str(d)).encode()) % 3 == 1) and 0 <= x["score"] <= 1 and x["predicted"] == (x["score"] >= 0.7) for d, x in got.items())
    held = [(got[i]["predicted"], t) for i, _, t in labels if got[i]["held_out"]]
    assert sum(p == t for p, t in held) / len(held) > 0.95 and got[None]["predicted"] == 1 and got[900]["predicted"] == 0
    assert toxicity.drop_toxic(df, lab).columns == df.columns
    assert toxicity.digest(df, lab.limit(0)).where("predicted = 1").count() == 0


def test_calibration_does_not_diverge():
    r = np.random.default_rng(0)
    for z, y in (
        (np.r_[r.normal(-40, 1, 300), r.normal(30, 1, 20)], np.r_[np.zeros(300), np.ones(20)]),
        (np.r_[r.normal(-2, 1, 300), r.normal(9, 30, 20)], np.r_[np.zeros(300), np.ones(20)]),
        (np.zeros(50), np.r_[np.zeros(45), np.ones(5)]),
    ):
        a, b = toxicity._calibrate(z, y.astype(int))
        assert abs(a) < 100 and abs(b) < 1_000
        assert ((a * z + b > 0)[y == 0]).mean() < 0.05


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "decontamination", "mixing", "sharding"]
    out = corpus_pipeline.run(spark, sf)
    ids = {r["doc_id"] for r in out.select("doc_id").collect()}
    bench = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    kept = [tuple(r) for r in docs.where(F.col("doc_id").isin(list(ids))).collect()]
    assert 0 < len(ids) == out.count() < docs.count() and not any(x[4] for x in brute_hits(kept, bench).values())
    n = [r["count"] for r in out.groupBy("shard").count().collect()]
    assert max(n) - min(n) <= 1


# --- any columns, any rows ----------------------------------------------------------------------

#: Names that the operators use inside, or give to what they add.
CLASHING = ["row", "size", "first", "share", "start", "lot", "block", "pos", "slot", "shard", "place", "curve", "s", "h", "c", "t", "n", "w", "b", "n0", "b0", "n1", "hi", "sub", "tie", "digest", "at", "of", "places", "release", "deadline", "score", "scan", "_scan", "lines", "th", "th2", "id2", "gone", "_gone", "fp", "nid", "key", "items", "spans", "starts", "removed", "kept_text", "n_words", "n_lines", "n_dropped", "n_removed", "_norm", "_all", "detections", "mix_slot", "law", "m0", "code", "f0", "f1", "c0", "Label", "a.b", "a b", "x`y"]


def crowded(spark):
    """Documents with every clashing name, nulls, empty, repeated and long texts."""
    rows = [(r[0], r[1], r[2], r[3], r[4], *[f"{c}-{i}" for c in CLASHING]) for i, r in enumerate(awkward(5, 12))]
    rows += [rows[3], rows[3], (900, "word " * 30_000, "en", None, 1, *CLASHING), (901, None, None, "s0", None, *[None] * len(CLASHING))]
    names = [f"`{c.replace('`', '``')}` string" for c in CLASHING]
    return spark.createDataFrame(rows, ", ".join([KINDS, *names])).repartition(3)


def operators(spark):
    bench = spark.createDataFrame([(1, "one"), (2, None)], "item_id long, text string")
    labels = spark.createDataFrame([(i, 1, int(i % 3 == 0)) for i in range(40)] + [(None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")
    return {
        "mix": lambda d: pfair.mix(d, {"s0": 2}), "mixed": pfair.mixed, "shard": lambda d: hilbert.shard(d, ["source", "lang", "n_chars"]), "shard_bytes": lambda d: hilbert.shard(d, ["source", "n_chars"], law="bytes", size=F.col("n_chars")),
        "scan": lambda d: decontamination.scan(d, bench), "drop": lambda d: decontamination.decontaminate(d, bench), "spans": lambda d: decontamination.decontaminate(d, bench, mode="spans"), "parts": lambda d: decontamination.decontaminate(d, bench, max_part_bytes=2),
        "keep_one": near_duplicates.keep_one, "detect": licenses.detect, "lines": lambda d: line_dedup.dedup_lines(d, bits=21), "substrings": lambda d: substring_dedup.dedup_substrings(d, bits=21), "toxic": lambda d: toxicity.drop_toxic(d, labels),
    }


#: What each adds; columns of these names give way to it.
ADDED = {"mix": ["block", "pos", "release", "deadline", "slot"], "shard": ["curve", "place", "shard", "slot"], "shard_bytes": ["curve", "place", "shard", "slot"], "scan": ["scan"], "detect": ["_norm", "detections"], "lines": ["n_lines", "n_dropped", "kept_text"], "substrings": ["n_words", "n_removed", "removed", "kept_text"]}


@pytest.fixture(scope="module")
def crowd(spark):
    return crowded(spark).cache()


@pytest.mark.parametrize("name", ["mix", "mixed", "shard", "shard_bytes", "scan", "drop", "spans", "parts", "keep_one", "detect", "lines", "substrings", "toxic"])
def test_clashing_columns(spark, crowd, name):
    run, added = operators(spark)[name], ADDED.get(name, [])
    out = run(crowd)
    kept = [c for c in crowd.columns if c not in added]
    assert sorted(out.columns) == sorted(kept + added)
    side = lambda d: Counter(map(repr, d.select(*[F.col("`" + c.replace("`", "``") + "`") for c in kept if name not in ("spans",) or c != "text"]).collect()))
    got, want = side(out), side(crowd)
    assert got == want if name not in ("drop", "parts", "keep_one", "toxic") else got <= want and got
    assert run(crowd.limit(0)).count() == 0


def test_pipeline_with_clashing_columns(spark, crowd, tmp_path):
    import corpus_pipeline

    crowd.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, "one")], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    spark.createDataFrame([(i, 1, int(i % 3 == 0)) for i in range(40)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    docs = crowd
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        docs = stage(spark, docs, str(tmp_path))
        if name != "sharding":
            assert docs.columns == crowd.columns
        docs.write.parquet(str(tmp_path / f"out{i}"))
        docs = spark.read.parquet(str(tmp_path / f"out{i}"))
    assert {"mix_slot", "curve", "place", "shard", "slot"} <= set(docs.columns) and docs.count() > 10
    order = [(r["shard"], r["mix_slot"]) for r in docs.select("shard", "mix_slot").collect()]
    spread = [max(m for s, m in order if s == x) - min(m for s, m in order if s == x) for x in {s for s, _ in order}]
    assert sum(spread) / len(spread) < max(m for _, m in order) + 1  # shards are stretches of the mix


def test_one_key_may_hold_half_of_the_rows(spark, monkeypatch):
    """Near copies of one text, far from each other: blocks of a bucket find every link, whatever the block size."""
    r = random.Random(4)
    base = [f"b{i}" for i in range(300)]
    rows = [(0, " ".join(base))]
    for k in range(1, 160):
        w = list(base)
        for _ in range(8):
            w[r.randrange(300)] = f"x{r.randrange(10**6)}"
        rows.append((k, " ".join(w)))
    rows += [(1000 + k, " ".join(f"z{r.randrange(10**6)}" for _ in range(40))) for k in range(160)]
    monkeypatch.setattr(near_duplicates, "BLOCK_ROWS", 16)
    monkeypatch.setattr(near_duplicates, "BLOCK_ITEMS", 3000)
    got = near_duplicates.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(4), shingle=2).collect()
    assert {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in got} == brute_components([(d, t) for d, t in rows], 2)


def test_common_counts():
    r = np.random.default_rng(0)
    sets = [np.unique(r.integers(0, 3000, r.integers(1, 2500))) for _ in range(30)]
    left, right = np.arange(0, 12), np.arange(12, 30)
    got = near_duplicates.common_counts(sets, left, right)
    assert all(got[i, j] == len(np.intersect1d(sets[a], sets[b])) for i, a in enumerate(left) for j, b in enumerate(right))
