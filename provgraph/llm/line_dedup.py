"""Line deduplication: Bloom filters pick suspects, an exact count confirms them.

Pass 1 fills the once- and twice-seen filters over line keys.  Pass 2 sends only lines whose key may
be in two documents through a shuffle, where the key's 128-bit digest is counted exactly over
documents and its smallest doc_id keeps the line.  Pass 3 drops the other documents' lines.
"""
from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.functions.columns import column, packed, unpacked
from provgraph.functions.ranking import salted_join
from provgraph.llm import bloom
from provgraph.llm.words import U64, bytes_of

MIN_CODE_POINTS = 10
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
_BLANK = b" \t\n\v\f\r"


def line_keys(text: bytes | None, least: int) -> list[bytes | None]:
    """A key per line; None where it is too short to count."""
    out = []
    for line in (text or b"").translate(_LOWER).split(b"\n"):
        k = line.strip(_BLANK)
        out.append(k if len(k) >= least and (len(k) >= 4 * least or len(k.decode()) >= least) else None)
    return out


def mark_repeats(docs: DataFrame, *, least: int = MIN_CODE_POINTS, bits: int = bloom.BITS) -> DataFrame:
    """(doc_id, th, lines): the 0-based lines that each document loses.  ``docs``: doc_id, text, th."""

    def keys(batch):
        pool, size = [], 0
        for t in bytes_of(batch.column("text")):
            pool += [xxhash.xxh3_64_intdigest(k) for k in set(line_keys(t, least)) if k is not None]
            if len(pool) > 200_000:
                yield np.array(pool, U64)
                pool = []
        yield np.array(pool, U64)

    held = docs.where("doc_id is not null")
    twice = docs.sparkSession.sparkContext.broadcast(bloom.twice_filter(held.select("text"), keys, bits))

    def suspects(batches):
        for batch in batches:
            texts, ids, ths = bytes_of(batch.column("text")), batch.column("doc_id"), batch.column("th")
            row, at, key = [], [], []
            for i, t in enumerate(texts):
                for j, k in enumerate(line_keys(t, least)):
                    if k is not None:
                        row.append(i)
                        at.append(j)
                        key.append(k)
            h = np.fromiter((xxhash.xxh3_64_intdigest(k) for k in key), U64, len(key))
            which = np.flatnonzero(bloom.member(twice.value, h, bits))
            rows = pa.array(np.array(row, np.int64)[which])
            digests = [hashlib.blake2b(key[i], digest_size=16).digest() for i in which]
            yield pa.RecordBatch.from_arrays([ids.take(rows), ths.take(rows), pa.array(np.array(at, np.int32)[which]), pa.array(digests, pa.binary())], ["doc_id", "th", "line", "key"])

    found = held.mapInArrow(suspects, "doc_id long, th long, line int, key binary")
    first = found.groupBy("key").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").select(F.col("key").alias("k"), "first")
    return salted_join(found, first, "key", "k", F.xxhash64("doc_id")).where("doc_id > first").groupBy("doc_id", "th").agg(F.collect_set("line").alias("lines"))


def dedup_lines(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """``docs`` with n_lines, n_dropped and kept_text.

    A null or empty text is one empty line.  Documents with a null id keep all lines and count
    nowhere.  Rows with one id and one text are one document given several times: each loses the
    same lines.  An empty table gives an empty table.  Columns of the same name as an added one are
    replaced by it.
    """
    base = docs.select(column(id_col).cast("long").alias("doc_id"), column(text).alias("text"), F.xxhash64(column(text)).alias("th"))
    lost = mark_repeats(base, **options).select(F.col("doc_id").alias("id2"), F.col("th").alias("th2"), "lines")
    rows = packed(docs, id=column(id_col).cast("long"), th=F.xxhash64(column(text)))
    said = F.coalesce(F.col("row").getField(text), F.lit(""))
    lines = F.split(said, "\n", -1)
    joined = rows.join(lost, (F.col("id") == F.col("id2")) & (F.col("th") == F.col("th2")), "left")
    kept = F.when(F.col("lines").isNull(), said).otherwise(F.array_join(F.filter(lines, lambda x, i: ~F.array_contains("lines", i)), "\n"))
    return unpacked(joined, docs.columns, n_lines=F.size(lines).cast("long"), n_dropped=F.when(F.col("lines").isNull(), 0).otherwise(F.size("lines")).cast("long"), kept_text=kept)


def digest(docs: DataFrame, **options) -> DataFrame:
    out = dedup_lines(docs.select("doc_id", "text"), **options)
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))
