"""Benchmark decontamination: test n-grams in a broadcast hash set, scanned for in training texts.

The benchmark's texts are cut into pieces of bounded size (neighbours share n - 1 words, so no window is
lost) and the pieces dealt into parts of at most about ``MAX_PART_BYTES``.  A part is fetched, broadcast,
scanned for and let go before the next one comes, so that the driver and each worker hold one part at a
time, whatever the benchmark's size.  A window found by hash is verified word for word before it counts.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.functions.columns import column, free_name, mapped, schema_with
from provgraph.functions.durable import cut_table
from provgraph.llm.words import ALNUM_LOWER, U64, Block, blocks, bytes_of, window_hashes

N = 10
MAX_PART_BYTES = 8 << 20
PIECE_WORDS = 4096
SCAN = "struct<n_words:bigint,n_hit:bigint,items:array<string>,spans:array<struct<lo:int,hi:int>>>"
KIND = pa.struct([("n_words", pa.int64()), ("n_hit", pa.int64()), ("items", pa.list_(pa.string())), ("spans", pa.list_(pa.struct([("lo", pa.int32()), ("hi", pa.int32())])))])
MAYBE_BITS = 22


class NgramSet:
    """The n-grams of some items as sorted hashes, each with where it stands; an item of fewer than n words is one window."""

    def __init__(self, items: list[tuple[str | None, bytes]], n: int):
        self.names = [name for name, _ in items]
        b = self.words = Block([text for _, text in items], ALNUM_LOWER)
        h, doc, last = b.hashes(), b.doc(), np.repeat(b.first[1:], b.count)
        self.by_size = {}
        for size in sorted({min(n, int(k)) for k in b.count if k}):
            at = np.arange(max(0, len(h) - size + 1))
            at = at[(at + size <= last[at]) & ((size == n) | (b.count[doc[at]] == size))]
            key = window_hashes(h, size)[at]
            maybe = np.zeros(1 << MAYBE_BITS, bool)
            maybe[(key >> U64(64 - MAYBE_BITS)).astype(np.int64)] = True
            o = np.argsort(key, kind="stable")
            self.by_size[size] = (maybe, key[o], at[o], doc[at[o]])

    def find(self, b: Block) -> tuple[np.ndarray, list[set]]:
        """Which words are hit, and the items of each text."""
        hit, items = np.zeros(len(b.s) + 1, np.int64), [set() for _ in b.count]
        h, doc, last, own = b.hashes(), b.doc(), np.repeat(b.first[1:], b.count), self.words
        known: dict[bytes, set | None] = {}
        for size, (maybe, key, at, owner) in self.by_size.items():
            got = window_hashes(h, size)
            near = np.flatnonzero(maybe[(got >> U64(64 - MAYBE_BITS)).astype(np.int64)])
            near = near[near + size <= last[near]]
            lo, hi = np.searchsorted(key, got[near], "left"), np.searchsorted(key, got[near], "right")
            for i, a, z in zip(near[lo < hi], lo[lo < hi], hi[lo < hi]):
                said = b" ".join(b.raw[b.s[i] : b.e[i + size - 1]].split())
                if said not in known:
                    same = [int(owner[k]) for k in range(a, z) if own.raw[own.s[at[k]] : own.e[at[k] + size - 1]] == said]
                    known[said] = {self.names[k] for k in same} - {None} if same else None
                if known[said] is not None:
                    hit[i] += 1
                    hit[i + size] -= 1
                    items[doc[i]] |= known[said]
        return np.cumsum(hit[:-1]) > 0, items


def _pieces(benchmark: DataFrame, item_id: str, text: str, n: int) -> DataFrame:
    """(item, words): the items' words, one space between, in pieces of at most PIECE_WORDS windows."""

    def run(batches):
        for batch in batches:
            out: list[tuple] = []
            for name, t in zip(batch.column(0).to_pylist(), bytes_of(batch.column(1))):
                w = (t or b"").translate(ALNUM_LOWER).split()
                for i in range(0, max(1, len(w) - n + 1) if w else 0, PIECE_WORDS):
                    out.append((name, b" ".join(w[i : i + PIECE_WORDS + n - 1])))
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in out], pa.string()), pa.array([x for _, x in out], pa.binary())], ["item", "words"])

    return benchmark.select(column(item_id).cast("string"), column(text)).mapInArrow(run, "item string, words binary")


def _spans(b: Block, d: int, hit: np.ndarray) -> list[dict]:
    """The byte spans of the runs of hit words of text d."""
    i, j = b.first[d], b.first[d + 1]
    edge = np.diff(np.concatenate([[0], hit[i:j].astype(np.int8), [0]]))
    return [{"lo": int(b.s[i + x] - b.at[d]), "hi": int(b.e[i + y - 1] - b.at[d])} for x, y in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1))]


def _scanned(docs: DataFrame, text: str, out: str, sent) -> DataFrame:
    """``docs`` with ``out``, from one part that was broadcast."""
    names, at = docs.columns, docs.columns.index(text)

    def run(batches):
        for batch in batches:
            rows = []
            for _, _, b in blocks(bytes_of(batch.column(at)), ALNUM_LOWER):
                hit, items = sent.value.find(b)
                total = np.concatenate([[0], np.cumsum(hit)])
                for d, k in enumerate(b.count):
                    n_hit = int(total[b.first[d + 1]] - total[b.first[d]])
                    rows.append({"n_words": int(k), "n_hit": n_hit, "items": sorted(items[d]), "spans": _spans(b, d, hit) if n_hit else []})
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(rows, KIND)], [*names, out])

    return mapped(docs, run, schema_with(docs, **{out: SCAN}))


def _merged(docs: DataFrame, text: str, out: str, found: DataFrame) -> DataFrame:
    """``docs`` with ``out``, from the parts' findings (th, items, spans) by digest of the text."""
    by_text = found.groupBy("th").agg(F.sort_array(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), F.flatten(F.collect_list("spans")).alias("spans"))
    names = docs.columns
    key, items, spans = (free_name(names, x) for x in ("th", "items", "spans"))
    joined = docs.join(by_text.select(F.col("th").alias(key), F.col("items").alias(items), F.col("spans").alias(spans)), F.md5(column(text)) == F.col(key), "left").select(*map(column, names), items, spans)
    at = names.index(text)

    def run(batches):
        for batch in batches:
            rows, which, where = [], batch.column(len(names)).to_pylist(), batch.column(len(names) + 1).to_pylist()
            for lo, _, b in blocks(bytes_of(batch.column(at)), ALNUM_LOWER):
                hit = np.zeros(len(b.s) + 1, np.int64)
                for d in range(len(b.count)):
                    for x in where[lo + d] or []:
                        hit[np.searchsorted(b.s, b.at[d] + x["lo"])] += 1
                        hit[np.searchsorted(b.e, b.at[d] + x["hi"]) + 1] -= 1
                hit = np.cumsum(hit[:-1]) > 0
                rows += [{"n_words": int(k), "n_hit": int(hit[b.first[d] : b.first[d + 1]].sum()), "items": which[lo + d] or [], "spans": _spans(b, d, hit)} for d, k in enumerate(b.count)]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(rows, KIND)], [*names, out])

    return mapped(joined, run, schema_with(docs, **{out: SCAN}))


def scan(docs: DataFrame, benchmark: DataFrame, *, text: str = "text", item_id: str = "item_id", item_text: str = "text", n: int = N, max_part_bytes: int = MAX_PART_BYTES, out: str = "scan") -> DataFrame:
    """``docs`` with ``out``: n_words, n_hit, items (ids as strings, sorted) and hit byte spans.

    An item of fewer than n words, but not none, is one window.  Null texts have no words; a null
    item text gives no window; a window of an item with a null id is hit but names no item.  An
    empty benchmark hits nothing.  Columns of ``docs`` pass through, but for one named as ``out``,
    which is replaced; equal rows stay separate.
    """
    docs = docs.select(*[column(c) for c in docs.columns if c.lower() != out.lower()])
    pieces = cut_table(_pieces(benchmark, item_id, item_text, n))
    size = pieces.agg(F.sum(F.octet_length("words"))).first()[0] or 0
    parts = -(-size // max_part_bytes) or 1
    dealt = pieces.withColumn("p", F.pmod(F.xxhash64("words", "item"), F.lit(parts)))
    fetch = lambda p: docs.sparkSession.sparkContext.broadcast(NgramSet([(r["item"], bytes(r["words"])) for r in dealt.where(F.col("p") == p).toLocalIterator()], n))
    if parts == 1:
        return _scanned(docs, text, out, fetch(0))
    found = None
    texts = docs.select(column(text).alias("text"))
    for p in range(parts):
        sent = fetch(p)
        hits = _scanned(texts, "text", "s", sent).where("s.n_hit > 0").select(F.md5("text").alias("th"), "s.items", "s.spans").dropDuplicates(["th"])
        hits = cut_table(hits)
        sent.destroy()
        found = hits if found is None else found.union(hits)
    return _merged(docs, text, out, found)


def digest(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """One row per document: counts, the sorted item ids' digest, and whether it is contaminated; nulls and repeats as in ``scan``."""
    s = scan(docs.select("doc_id", "text"), benchmark, **options)
    listed = F.array_join("scan.items", ",")
    return s.select("doc_id", F.col("scan.n_words").alias("n_words"), F.col("scan.n_hit").alias("n_hit"), F.size("scan.items").cast("long").alias("n_items"), F.sha2(listed, 256).alias("items_sha256"), (F.col("scan.n_hit") > 0).alias("contaminated"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, *, mode: str = "drop", text: str = "text", **options) -> DataFrame:
    """``docs`` without contamination, with the same columns, whatever their names.

    ``drop`` removes contaminated documents; ``spans`` cuts the hit words out of their texts and
    keeps every document.  Nulls and repeats as in ``scan``.
    """
    if mode not in ("drop", "spans"):
        raise ValueError(f"mode {mode!r}")
    out = free_name(docs.columns, "scan")
    s, got = scan(docs, benchmark, text=text, out=out, **options), F.col(out)
    if mode == "drop":
        return s.where(got["n_hit"] == 0).select(*map(column, docs.columns))
    raw = F.encode(column(text), "utf-8")
    pieces = F.transform(
        F.arrays_zip(F.concat(F.array(F.lit(0)), got["spans"]["hi"]).alias("a"), F.concat(got["spans"]["lo"], F.array(F.octet_length(column(text)))).alias("b")),
        lambda z: F.decode(F.substring(raw, z["a"] + 1, z["b"] - z["a"]), "utf-8"),
    )
    cut = F.when(F.size(got["spans"]) > 0, F.array_join(pieces, "")).otherwise(column(text))
    return s.select(*[cut.alias(c) if c == text else column(c) for c in docs.columns])
