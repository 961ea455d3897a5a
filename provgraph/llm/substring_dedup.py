"""Substring deduplication by FM-indexes over shards of suspected passages.

Every window of 50 words belongs to the least-hashed group of 8 words in it (its minimizer), so
equal windows always share a minimizer, and a run of windows with one minimizer is one passage.
1. Two Bloom filters find minimizers that may be in two documents.
2. Passages of such minimizers are dealt to shards by minimizer; equal passages are combined first, with
   their smallest doc_id.  The passages of a minimizer that has very many different ones are cut again, by
   the least group in a second order of hashes, and where that isn't enough into single windows, so that
   no shard grows with one hot minimizer.
3. Each shard builds a compressed index of its passages and streams them through it: where the
   matching statistic reaches the window, the least doc_id of the match is known.
4. Documents with a larger doc_id lose the words of those windows, reported as intervals.
"""
from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.functions.columns import column, schema_with
from provgraph.functions.durable import cut, cut_table
from provgraph.llm import bloom
from provgraph.llm.fm_index import FMIndex
from provgraph.llm.words import BLANK, U64, Block, blocks, bytes_of, mix, window_hashes

WINDOW = 50
SEED_WORDS = 8
SHARD_BYTES = 1 << 19
HOT_PASSAGES = 2_000
OUT_ROWS = 500
#: The second order of hashes.
SALT = 0x2545F4914F6CDD1D


def _minima(h: np.ndarray, width: int) -> np.ndarray:
    """For each i the leftmost place of the least of h[i : i + width]."""
    n = len(h) - width + 1
    best, place, k = h, np.arange(len(h)), 1
    while 2 * k <= width:
        right = best[k:] < best[:-k]
        best, place = np.where(right, best[k:], best[:-k]), np.where(right, place[k:], place[:-k])
        k *= 2
    off = width - k
    return np.where(best[off : off + n] < best[:n], place[off : off + n], place[:n])


def passages(b, window: int, seed: int, salt: int = 0):
    """(text, minimizer, first word, number of windows) of each run of windows with one minimizer, as arrays; ``salt`` gives another order of hashes."""
    h = window_hashes(b.hashes(), seed)
    if salt:
        h = mix(h ^ U64(salt))
    span = window - seed + 1
    if len(h) < span:
        return (np.empty(0, np.int64),) * 4
    least = _minima(h, span)
    starts = np.arange(len(least))
    doc, stop = b.doc()[: len(least)], np.repeat(b.first[1:], b.count)[: len(least)]
    inside = starts + window <= stop
    starts, least, doc = starts[inside], least[inside], doc[inside]
    new = np.flatnonzero(np.concatenate([[True], (least[1:] != least[:-1]) | (doc[1:] != doc[:-1])])) if len(starts) else np.empty(0, np.int64)
    return doc[new], h[least[new]], starts[new], np.diff(np.concatenate([new, [len(starts)]]))


def _suspects(docs: DataFrame, window: int, seed: int, bits: int) -> tuple[DataFrame, DataFrame]:
    """Passages whose minimizer may be in two documents: where they are, and what they say.

    The first table is (doc_id, th, at, seed, ch, size), the second (doc_id, seed, ch, content).  The
    words go into one shuffle and are never written, which costs a second reading of the texts.
    """

    def keys(batch):
        for _, _, b in blocks(bytes_of(batch.column("text")), BLANK):
            doc, m, _, _ = passages(b, window, seed)
            pair = np.unique(np.rec.fromarrays([doc, m])) if len(doc) else None
            if pair is not None:
                yield np.ascontiguousarray(pair["f1"])

    twice = docs.sparkSession.sparkContext.broadcast(bloom.twice_filter(docs.select("text"), keys, bits))

    def emit(batches, places: bool):
        for batch in batches:
            ids, ths = batch.column("doc_id"), batch.column("th")
            for lo, _, b in blocks(bytes_of(batch.column("text")), BLANK):
                doc, m, at, n = passages(b, window, seed)
                which = np.flatnonzero(bloom.member(twice.value, m, bits)) if len(m) else []
                doc, m, at, n = doc[which], m[which], at[which], n[which]
                content = [b" ".join(b.raw[b.s[i] : b.e[i + k + window - 2]].split()) for i, k in zip(at, n)]
                ch = pa.array([hashlib.md5(c).digest() for c in content], pa.binary())
                row, seeds = pa.array(doc + lo), pa.array(m.view(np.int64))
                if places:
                    at, size = (at - b.first[doc]).astype(np.int32), np.array([len(c) for c in content], np.int32)
                    yield pa.RecordBatch.from_arrays([ids.take(row), ths.take(row), pa.array(at), seeds, ch, pa.array(size)], ["doc_id", "th", "at", "seed", "ch", "size"])
                else:
                    yield pa.RecordBatch.from_arrays([ids.take(row), seeds, ch, pa.array(content, pa.binary())], ["doc_id", "seed", "ch", "content"])

    where = docs.mapInArrow(lambda x: emit(x, True), "doc_id long, th long, at int, seed long, ch binary, size int")
    return where, docs.mapInArrow(lambda x: emit(x, False), "doc_id long, seed long, ch binary, content binary")


def search_shard(pdf: pd.DataFrame, window: int) -> pd.DataFrame:
    """Builds the shard's index and streams its passages through it: (content, firsts), the least doc_id per window."""
    number: dict[bytes, int] = {}
    texts = [np.array([number.setdefault(w, len(number) + 1) for w in c.split()], np.int64) for c in pdf["content"]]
    index = FMIndex(texts, pdf["owner"].to_numpy(np.int64), window)
    firsts = []
    for (length, owner), t in zip(index.matching_statistics(texts), texts):
        k = len(t) - window + 1
        assert (length[:k] >= window).all()
        firsts.append(owner[:k])
    return pd.DataFrame({"ch": pdf["ch"], "firsts": firsts})


def repeats(docs: DataFrame, *, window: int = WINDOW, seed: int = SEED_WORDS, bits: int = bloom.BITS, shard_bytes: int = SHARD_BYTES, hot: int = HOT_PASSAGES) -> DataFrame:
    """(doc_id, th, starts): windows of the document that a smaller doc_id has too.  ``docs``: doc_id, text, th."""
    seed = min(seed, window)
    occ, said = _suspects(docs.where("doc_id is not null"), window, seed, bits)
    occ = cut_table(occ)
    said = said.groupBy("seed", "ch").agg(F.min("doc_id").alias("owner"), F.first("content").alias("content"))
    # Different passages per minimizer, counted without their words.
    per_seed = occ.groupBy("seed", "ch").agg(F.first("size").alias("size")).groupBy("seed").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("size"))
    firsts = _resolve(said, per_seed, window, seed, shard_bytes, hot, 1).select(F.col("ch").alias("c"), "firsts")
    late = occ.select("doc_id", "th", "at", "ch").join(cut_table(firsts), F.col("ch") == F.col("c")).select("doc_id", "th", F.filter(F.transform("firsts", lambda f, i: F.when(f < F.col("doc_id"), F.col("at") + i)), lambda x: x.isNotNull()).alias("starts"))
    return late.where(F.size("starts") > 0).groupBy("doc_id", "th").agg(F.flatten(F.collect_list("starts")).alias("starts"))


def _resolve(said: DataFrame, per_seed: DataFrame, window: int, seed: int, shard_bytes: int, hot: int, level: int) -> DataFrame:
    """(ch, firsts) of the different passages (seed, ch, owner, content): the least owner of each window, by the shards' indexes.

    ``per_seed``: number and bytes of each seed's passages.  Those of hot seeds are cut smaller for the next level; single windows are the last.
    """
    is_hot = (F.col("n") > hot) if level < 3 else F.lit(False)
    hot_seeds = cut(per_seed.where(is_hot).select(F.col("seed").alias("s")))
    total = per_seed.where(~is_hot).agg(F.sum("size")).first()[0] or 0
    shards = max(1, -(-total // shard_bytes))
    some = hot_seeds.isEmpty()
    plain = said if some else said.join(_small(hot_seeds), F.col("seed") == F.col("s"), "left_anti")
    dealt = plain.select("ch", "owner", "content", F.pmod(F.xxhash64("seed"), F.lit(int(shards))).alias("shard"))
    firsts = dealt.groupBy("shard").applyInPandas(lambda pdf: search_shard(pdf, window), "ch binary, firsts array<bigint>")
    if some:
        return firsts

    def smaller(rows):
        for pdf in rows:
            out = []
            for ch, owner, content, old in zip(pdf["ch"], pdf["owner"], pdf["content"], pdf["seed"]):
                w = content.split()
                if level == 1:
                    _, m, at, n = passages(Block([content], BLANK), window, seed, SALT)
                    cuts = [(int(k) ^ old & 0xFFFFFFFFFFFFFFFF, int(i), int(c)) for k, i, c in zip(m, at, n)]
                else:
                    cuts = [(None, i, 1) for i in range(len(w) - window + 1)]
                for key, i, c in cuts:
                    one = b" ".join(w[i : i + c + window - 1])
                    d = hashlib.md5(one).digest()
                    out.append((ch, owner, i, one, d, np.uint64(key if key is not None else int.from_bytes(d[:8], "big")).astype(np.int64)))
            yield pd.DataFrame(out, columns=["ch", "owner", "i", "content", "sub", "seed"])

    cuts = cut_table(said.join(_small(hot_seeds), F.col("seed") == F.col("s"), "left_semi").select("ch", "owner", "content", "seed").mapInPandas(smaller, "ch binary, owner long, i int, content binary, sub binary, seed long"))
    once = cuts.groupBy("seed", F.col("sub").alias("ch")).agg(F.min("owner").alias("owner"), F.first("content").alias("content"))
    sizes = cuts.groupBy("seed", "sub").agg(F.first(F.octet_length("content")).alias("size")).groupBy("seed").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("size"))
    found = _resolve(once, cut_table(sizes), window, seed, shard_bytes, hot, level + 1).select(F.col("ch").alias("w"), F.col("firsts").alias("got"))
    back = cuts.select("ch", "i", "sub").join(cut_table(found), F.col("sub") == F.col("w")).groupBy("ch").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("i", "got"))), lambda x: x["got"])).alias("firsts"))
    return firsts.unionByName(back)


def _small(df: DataFrame, rows: int = 100_000) -> DataFrame:
    """``df`` marked for broadcast if it is counted to be small (2 MB); beyond that Spark chooses the join."""
    return F.broadcast(df) if df.count() <= rows else df


def dedup_substrings(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", window: int = WINDOW, columns: list[str] | None = None, **options) -> DataFrame:
    """``docs`` (or only its ``columns``) with n_words, n_removed, removed (intervals [lo, hi) of words) and kept_text (kept words joined by one space).

    A null text has no words.  Documents with a null id, and windows shared only by rows of one id,
    lose nothing.  Rows with one id and one text lose the same words.  Columns of the same name as an
    added one are replaced by it; an empty table stays empty.
    """
    base = docs.select(column(id_col).cast("long").alias("doc_id"), column(text).alias("text"), F.xxhash64(column(text)).alias("th"))
    lost = repeats(base, window=window, **options)
    names = [c for c in (docs.columns if columns is None else columns) if c.lower() not in ("n_words", "n_removed", "removed", "kept_text")]
    flat = docs.select(column(text), column(id_col).cast("long"), F.xxhash64(column(text)), *map(column, names)).toDF("f0", "f1", "f2", *[f"c{i}" for i in range(len(names))])
    joined = flat.join(lost, (F.col("f1") == F.col("doc_id")) & (F.col("f2") == F.col("th")), "left").select("f0", "starts", *[f"c{i}" for i in range(len(names))])
    schema = schema_with(docs.select(*map(column, names)), n_words="long", n_removed="long", removed="array<struct<lo:int,hi:int>>", kept_text="string")
    for f in schema:
        f.nullable = True
    spans = pa.list_(pa.struct([("lo", pa.int32()), ("hi", pa.int32())]))

    def kept_words(t, starts):
        words = (t or b"").split()
        n, removed = len(words), []
        if starts.is_valid:
            mark = np.zeros(n + 1, np.int32)
            at = starts.values.to_numpy(zero_copy_only=False)
            np.add.at(mark, at, 1)
            np.add.at(mark, at + window, -1)
            gone = np.cumsum(mark[:-1]) > 0
            edge = np.diff(np.concatenate([[0], gone.astype(np.int8), [0]]))
            removed = [{"lo": int(a), "hi": int(b)} for a, b in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1))]
            words = [words[i] for i in np.flatnonzero(~gone)]
        return n, n - len(words), removed, b" ".join(words)

    def run(batches):
        for batch in batches:
            for lo in range(0, len(batch), OUT_ROWS):  # small batches go back, whatever came
                part = batch.slice(lo, OUT_ROWS)
                got = [kept_words(t, s) for t, s in zip(bytes_of(part.column(0)), part.column(1))]
                kept = pa.array([g[3] for g in got], pa.binary()).cast(pa.string())
                yield pa.RecordBatch.from_arrays([*part.columns[2:], pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.int64()), pa.array([g[2] for g in got], spans), kept], [*names, "n_words", "n_removed", "removed", "kept_text"])

    return joined.mapInArrow(run, schema)


def digest(docs: DataFrame, **options) -> DataFrame:
    """The counts and the digest of the kept words of every document; nulls, repeats and empty tables as in ``dedup_substrings``."""
    out = dedup_substrings(docs.select("doc_id", "text"), columns=["doc_id"], **options)
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))
