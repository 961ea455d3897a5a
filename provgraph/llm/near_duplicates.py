"""MinHash near-duplicates by a multi-index Hamming join over b-bit signatures.

A document's set of word shingles has a signature of 8 chunks of 5 values of 16 bits.  Two
signatures that differ in at most 15 of 40 values have, by the pigeonhole principle, a chunk with at
most one difference; every chunk therefore gives one key for each value left out, and equal keys make
candidates.  (At similarity 0.8 a pair lacks such a chunk with probability 2e-5, at 0.85 with 5e-7.)
Equal sets meet before that.  Small buckets of equal keys are compared pair by pair; a member of larger
ones is compared with the least and the greatest hub of its buckets.  Where a bucket then still holds
several components, blocks bounded by rows and by shingles compare members of different components,
first by signature, then on full sets; rows of the bucket's largest component meet only the others.
Links are confirmed on full sets.
"""
from __future__ import annotations

import hashlib
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.functions.columns import column, free_name
from provgraph.functions.durable import cut_table
from provgraph.functions.ranking import salted_join
from provgraph.llm.words import BLANK_LOWER, U64, blocks, bytes_of, mix
from provgraph.operators.components import connected

CHUNKS, VALUES, ERRORS = 8, 5, 1
SIZE = CHUNKS * VALUES
#: Pairs whose signatures differ in more values are taken as unlinked: at similarity 0.8 that has probability 2e-6.
MOST_DIFFERENT = 20
#: A block of a bucket: rows, and shingles in all (a set beyond that is alone).
BLOCK_ROWS, BLOCK_ITEMS = 512, 1 << 18
#: Buckets of so few members are compared pair by pair.
FEW = 3
BROADCAST_ROWS = 100_000
_SEEDS = mix(np.arange(1, SIZE + 1, dtype=U64)) | U64(1)
_KEPT = [(c, [c * VALUES + v for v in keep]) for c in range(CHUNKS) for keep in combinations(range(VALUES), VALUES - ERRORS)]
_CHUNK_OF = np.array([c for c, _ in _KEPT])
_COEF = mix(np.arange(101, 101 + VALUES, dtype=U64)) | U64(1)


def shingle_sets(b, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, first): the sorted distinct shingle hashes of each text of the block."""
    h = b.hashes()
    m = len(h)
    coef = mix(np.arange(7, 7 + n, dtype=U64)) | U64(1)
    rolled = np.zeros(m, U64)
    for k in range(n):
        rolled[: m - k] += h[k:] * coef[k]
    rolled = mix(rolled)
    out, first = [], [0]
    for d, k in enumerate(b.count):
        i = b.first[d]
        if k == 0:
            s = rolled[:0]
        elif k < n:
            s = mix((h[i : i + k] * coef[:k]).sum(keepdims=True, dtype=U64) + U64(k))
        else:
            s = np.sort(rolled[i : i + k - n + 1])
            s = s[np.concatenate([[True], s[1:] != s[:-1]])]
        out.append(s)
        first.append(first[-1] + len(s))
    return np.concatenate(out) if out else rolled[:0], np.array(first)


def _signed(batches, n):
    for batch in batches:
        ids, ths = batch.column("doc_id"), batch.column("th")
        for lo, hi, b in blocks(bytes_of(batch.column("text")), BLANK_LOWER):
            sets, first = shingle_sets(b, n)
            size = np.diff(first)
            some = np.flatnonzero(size)
            values = np.zeros((len(size), SIZE), np.uint16)
            if len(some):
                for j, a in enumerate(_SEEDS):
                    values[some, j] = mix(np.minimum.reduceat(sets * a, first[some])) & U64(0xFFFF)
            wide = values.astype(U64) + U64(1)
            keys = np.stack([mix((wide[:, at] * _COEF[: len(at)]).sum(axis=1, dtype=U64) + U64(j + 1) * U64(0x9E3779B97F4A7C15)) for j, (_, at) in enumerate(_KEPT)], axis=1)
            mark = [hashlib.blake2b(sets[first[i] : first[i + 1]].tobytes(), digest_size=16).digest() for i in range(len(size))]
            offsets = pa.array(np.arange(len(size) + 1, dtype=np.int32) * len(_KEPT))
            yield pa.RecordBatch.from_arrays(
                [ids.slice(lo, hi - lo), ths.slice(lo, hi - lo), pa.array(size.astype(np.int64)), pa.array(mark, pa.binary()), pa.array([v.tobytes() for v in values], pa.binary()), pa.ListArray.from_arrays(offsets, pa.array(keys.view(np.int64).ravel()))],
                ["doc_id", "th", "n", "fp", "sig", "keys"],
            )


def _sets_of(docs: DataFrame, wanted: DataFrame, n: int) -> DataFrame:
    """(fp, items) of the wanted (fp, th, id), computed again from the texts."""
    wanted = cut_table(wanted)
    w = wanted.select(F.col("th").alias("_th"), F.col("min_id").alias("_id"), F.col("fp").alias("_fp"))
    if wanted.count() <= BROADCAST_ROWS:  # at most 4 MB; beyond it a shuffled join
        w = F.broadcast(w)
    texts = docs.join(w, (F.col("th") == F.col("_th")) & F.col("doc_id").eqNullSafe(F.col("_id"))).select("_fp", "text")

    def run(batches):
        for batch in batches:
            for lo, hi, b in blocks(bytes_of(batch.column("text")), BLANK_LOWER):
                sets, first = shingle_sets(b, n)
                items = pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(sets.view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column("_fp").slice(lo, hi - lo), items], ["fp", "items"])

    found = texts.mapInArrow(run, "fp binary, items array<bigint>")
    return found.groupBy("fp").agg(F.first("items").alias("items"))


def _first_here(a: np.ndarray, b: np.ndarray, at: int) -> np.ndarray:
    """Which pairs of signatures (rows of a and b) are near and have key ``at`` as the first that they share."""
    other = a != b
    in_chunk = other.reshape(len(other), CHUNKS, VALUES).sum(axis=2, dtype=np.uint8)
    out = (in_chunk.sum(axis=1) <= MOST_DIFFERENT) & ((in_chunk <= ERRORS).argmax(axis=1) == _CHUNK_OF[at])
    some = np.flatnonzero(out)
    earlier = [k for k in range(at) if _CHUNK_OF[k] == _CHUNK_OF[at]]
    shares = lambda k: ~other[some][:, _KEPT[k][1]].any(axis=1)
    first = shares(at)
    for k in earlier:
        first &= ~shares(k)
    out[some] = first
    return out


def common_counts(sets: list[np.ndarray], left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Sizes of the intersections of sets[left] with sets[right]: products of 0/1 matrices, some shared items at a time."""
    both = np.zeros((len(left), len(right)), np.int64)
    items, col = np.unique(np.concatenate([np.asarray(x, np.int64) for x in sets]), return_inverse=True)
    row = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    held = np.bincount(col, minlength=len(items)) > 1
    number = np.cumsum(held) - 1
    some = held[col]
    row, col = row[some], number[col[some]]
    o = np.argsort(col, kind="stable")
    row, col = row[o], col[o]
    for lo in range(0, int(held.sum()), 1024):
        a, b = np.searchsorted(col, [lo, lo + 1024])
        m = np.zeros((len(sets), 1024), np.float32)
        m[row[a:b], col[a:b] - lo] = 1
        both += (m[left] @ m[right].T).astype(np.int64)
    return both


def near_duplicates(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", shingle: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of ``docs``.

    Documents link where 100 * |intersection| >= percent * |union| of their distinct shingles; one
    with fewer words than a shingle has its whole sequence as the only one.  Texts without words, and
    null texts, have empty sets and link with nothing.  Rows with a null id have a null component
    unless they share one with rows that have an id.  Equal rows stay separate rows.
    """
    base = docs.select(column(id_col).cast("long").alias("doc_id"), column(text).alias("text"), F.xxhash64(column(text)).alias("th"))
    signed = cut_table(base.mapInArrow(lambda batches: _signed(batches, shingle), "doc_id long, th long, n long, fp binary, sig binary, keys array<bigint>"))
    best = F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "th"))
    groups = signed.where("n > 0").groupBy("fp").agg(best.alias("b"), F.first("n").alias("n"), F.first("sig").alias("sig"), F.first("keys").alias("keys"))
    groups = cut_table(groups.select("fp", F.xxhash64("fp").alias("nid"), F.col("b.doc_id").alias("min_id"), F.col("b.th").alias("th"), "n", "sig", "keys"))

    # Sets of k shingles can only link with sets of at least k * percent / 100: small ones with equal sets alone.
    least = next(k for k in range(1, 200) if 100 * k >= percent * (k + 1))
    keyed = groups.where(F.col("n") >= least).select("nid", F.posexplode("keys").alias("at", "key"))
    ends = keyed.groupBy("key").agg(F.min("nid").alias("low"), F.max("nid").alias("high"), F.count(F.lit(1)).alias("held")).where("low < high")
    # Both sides are tables without a partitioning, so that the join of a hot key can be split.
    members = cut_table(keyed.join(cut_table(ends.withColumnRenamed("key", "_key")), F.col("key") == F.col("_key")).drop("_key"))
    both_ends = F.explode(F.array(F.struct(F.col("low").alias("hub")), F.struct(F.col("high").alias("hub")))).alias("e")
    few = members.where(F.col("held") <= FEW).select("nid", "low", "high")
    many = members.where(F.col("held") > FEW).groupBy("nid").agg(F.min("low").alias("low"), F.max("high").alias("high"))
    pairs = few.union(many).select("nid", both_ends).where("nid <> e.hub").select("nid", F.col("e.hub").alias("hub")).distinct()
    about = groups.select("nid", "fp", "n", "sig", "th", "min_id")
    side = lambda x: about.select(F.col("nid").alias(f"_{x}"), *[F.col(c).alias(f"{c}_{x}") for c in ("fp", "n", "sig", "th", "min_id")])
    differ = F.aggregate(F.sequence(F.lit(0), F.lit(SIZE - 1)), F.lit(0), lambda acc, i: acc + (F.substring("sig_a", 2 * i + 1, F.lit(2)) != F.substring("sig_b", 2 * i + 1, F.lit(2))).cast("int"))
    near = pairs.join(side("b"), F.col("nid") == F.col("_b")).join(side("a"), F.col("hub") == F.col("_a"))
    near = near.where((100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b")) & (differ <= MOST_DIFFERENT))
    near = cut_table(near.select("fp_a", "th_a", "min_id_a", "fp_b", "th_b", "min_id_b"))

    either = lambda x: near.select(F.col(f"fp_{x}").alias("fp"), F.col(f"th_{x}").alias("th"), F.col(f"min_id_{x}").alias("min_id"))
    sets = cut_table(_sets_of(base, either("a").union(either("b")).distinct(), shingle))
    one = lambda x: sets.select(F.col("fp").alias(f"f_{x}"), F.col("items").alias(f"items_{x}"))
    both = F.size(F.array_intersect("items_a", "items_b"))
    # Members fetch their own sets first; a hub's set then comes once to its members, and never travels with them.
    full = near.select("fp_a", "fp_b").join(one("b"), F.col("fp_b") == F.col("f_b")).join(one("a"), F.col("fp_a") == F.col("f_a"))
    links = cut_table(full.where(100 * both >= percent * (F.size("items_a") + F.size("items_b") - both)).select(F.col("fp_a").alias("src"), F.col("fp_b").alias("dst")))
    comp = cut_table(connected(links))

    # Larger buckets that still hold several components: compare across them, in blocks.
    number = lambda c: F.xxhash64(F.coalesce("component", c))  # noqa: E731  equal numbers of unequal components: 2**-64
    placed = cut_table(groups.join(comp, F.col("fp") == F.col("node"), "left").select(F.col("nid").alias("_nid"), "fp", "n", "sig", "th", "min_id", number("fp").alias("comp")))
    rest = cut_table(members.where(F.col("held") > FEW).select("key", "at", "nid").join(placed, F.col("nid") == F.col("_nid")).drop("_nid"))
    shares = rest.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("rows"), F.sum("n").alias("items"))
    mixed = shares.groupBy("key").agg(F.max_by("comp", F.struct("rows", "comp")).alias("main"), F.count(F.lit(1)).alias("comps"), F.sum("rows").alias("rows"), F.sum("items").alias("items"), F.max("rows").alias("in_main"), F.max_by("items", F.struct("rows", "comp")).alias("main_items")).where("comps > 1")
    blocks_of = lambda rows, items: F.greatest(F.ceil(rows / BLOCK_ROWS), F.ceil(items / BLOCK_ITEMS)).cast("int")
    mixed = cut_table(mixed.select(F.col("key").alias("_key"), "main", blocks_of(F.col("rows") - F.col("in_main"), F.col("items") - F.col("main_items")).alias("q"), blocks_of(F.col("in_main"), F.col("main_items")).alias("p")))
    rest = rest.join(mixed, F.col("key") == F.col("_key"))
    # The component with most rows is blocks q.., all others are blocks 0..q - 1: two blocks meet unless both are of the first kind.
    in_main = F.col("comp") == F.col("main")
    own = F.when(in_main, F.col("q") + F.pmod(F.xxhash64("nid"), F.col("p").cast("long"))).otherwise(F.pmod(F.xxhash64("nid"), F.col("q").cast("long"))).cast("int")
    others = F.sequence(F.lit(0), F.when(in_main, F.col("q") - 1).otherwise(F.col("q") + F.col("p") - 1))
    spots = F.transform(others, lambda j: F.struct(F.least("own", j).alias("i"), F.greatest("own", j).alias("j")))
    dealt = rest.withColumn("own", own).withColumn("spot", F.explode(spots)).select("key", F.col("spot.i").alias("i"), F.col("spot.j").alias("j"), "own", "at", "fp", "n", "sig", "comp", "th", "min_id")

    def unsettled(pdf: pd.DataFrame) -> pd.DataFrame:
        sig = np.frombuffer(b"".join(pdf["sig"]), np.uint16).reshape(len(pdf), SIZE)
        n, comp, own = pdf["n"].to_numpy(), pd.factorize(pdf["comp"])[0], pdf["own"].to_numpy()
        keep, at = np.zeros(len(pdf), bool), int(pdf["at"].iloc[0])
        left, right = np.flatnonzero(own == pdf["i"].iloc[0]), np.flatnonzero(own == pdf["j"].iloc[0])
        for i in range(0, len(left), 64):
            rows = left[i : i + 64]
            ok = comp[rows, None] != comp[None, right]
            ok &= 100 * np.minimum(n[rows, None], n[None, right]) >= percent * np.maximum(n[rows, None], n[None, right])
            r, c = np.nonzero(ok)
            for k in range(0, len(r), 16_384):
                a, b = rows[r[k : k + 16_384]], right[c[k : k + 16_384]]
                here = _first_here(sig[a], sig[b], at)
                keep[a[here]] = True
                keep[b[here]] = True
        return pdf.loc[keep, ["key", "i", "j", "own", "fp", "comp", "th", "min_id"]]

    # Dealt by block: rows that came by key would bring all blocks of a key to one task.
    tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = dealt.repartition(tasks, "key", "i", "j")
    open_rows = cut_table(dealt.groupBy("key", "i", "j").applyInPandas(unsettled, "key long, i int, j int, own int, fp binary, comp long, th long, min_id long"))
    if not open_rows.isEmpty():
        more = _sets_of(base, open_rows.select("fp", "th", "min_id").distinct(), shingle).select(F.col("fp").alias("f"), "items")
        rows = open_rows.join(more, F.col("fp") == F.col("f")).select("key", "i", "j", "own", "fp", "comp", "items")

        def settle(pdf: pd.DataFrame) -> pd.DataFrame:
            own, fp, size = pdf["own"].to_numpy(), list(pdf["fp"]), np.fromiter(map(len, pdf["items"]), np.int64, len(pdf))
            left, right = np.flatnonzero(own == pdf["i"].iloc[0]), np.flatnonzero(own == pdf["j"].iloc[0])
            comp, out = pd.factorize(pdf["comp"])[0].copy(), []
            both = common_counts(list(pdf["items"]), left, right)
            linked = 100 * both >= percent * (size[left, None] + size[None, right] - both)
            for r, a in enumerate(left):
                near = right[linked[r]]
                for c in np.setdiff1d(comp[near], comp[a]):
                    out.append((fp[a], fp[near[comp[near] == c][0]]))
                    comp[comp == c] = comp[a]
            return pd.DataFrame(out, columns=["src", "dst"])

        late = rows.repartition(tasks, "key", "i", "j").groupBy("key", "i", "j").applyInPandas(settle, "src binary, dst binary")
        comp = cut_table(connected(links.union(late)))

    named = groups.join(comp, F.col("fp") == F.col("node"), "left").select(F.col("fp").alias("_fp"), "min_id", F.coalesce("component", "fp").alias("comp"))
    smallest = named.groupBy("comp").agg(F.min("min_id").alias("component_id"))
    named = salted_join(named, smallest.withColumnRenamed("comp", "_comp"), "comp", "_comp", F.xxhash64("_fp")).select("_fp", "component_id")
    out = signed.select("doc_id", "n", "fp").join(named, F.col("fp") == F.col("_fp"), "left")
    component = F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), component.eqNullSafe(F.col("doc_id")).alias("kept"))


def keep_one(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """``docs`` with one document of each near-duplicate group: the one with the smallest id; same columns, whatever their names."""
    gone = free_name(docs.columns, "gone")
    found = near_duplicates(docs, id_col=id_col, text=text, **options).where("not kept").select(F.col("doc_id").alias(gone)).distinct()
    return docs.join(cut_table(found), column(id_col).cast("long") == F.col(gone), "left_anti")
