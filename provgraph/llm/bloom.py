"""Two Bloom filters over all rows: keys seen in at least one document, and in at least two.

Every task fills its own pair; the pairs meet segment by segment (a segment is a fixed slice of the
bits), where a bit set in both once-filters goes to the twice-filter.  No key that two documents
hold is ever missed; false positives only let more rows through.  The merged twice-filter has a
fixed size, so broadcasting it has a proven bound.
"""
from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.llm.words import U64

BITS = 27
SEGMENT_BITS = 20


def places(h: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    mask = U64((1 << bits) - 1)
    return h & mask, (h >> U64(32)) * U64(0x9E3779B1) + (h >> U64(7)) & mask


def _set(f: np.ndarray, p: np.ndarray) -> None:
    p = np.sort(p)
    byte, value = (p >> U64(3)).astype(np.int64), (np.uint8(1) << (p & U64(7)).astype(np.uint8))
    if len(byte):
        at = np.flatnonzero(np.concatenate([[True], byte[1:] != byte[:-1]]))
        f[byte[at]] |= np.bitwise_or.reduceat(value, at)


def member(f: np.ndarray, h: np.ndarray, bits: int) -> np.ndarray:
    a, b = places(h, bits)
    one = lambda p: (f[(p >> U64(3)).astype(np.int64)] >> (p & U64(7)).astype(np.uint8)) & 1
    out = one(a).astype(bool)
    if out.any():
        out[out] = one(b[out]).astype(bool)
    return out


class Pair:
    def __init__(self, bits: int):
        self.bits, self.once, self.twice = bits, np.zeros(1 << bits - 3, np.uint8), np.zeros(1 << bits - 3, np.uint8)

    def add(self, h: np.ndarray) -> None:
        """Adds keys of different documents or batches; a key given several times here is held by several documents."""
        h, n = np.unique(h, return_counts=True)
        again = h[(n > 1) | member(self.once, h, self.bits)]
        for p in places(again, self.bits):
            _set(self.twice, p)
        for p in places(h, self.bits):
            _set(self.once, p)


def twice_filter(docs: DataFrame, keys: Callable[[pa.RecordBatch], Iterator[np.ndarray]], bits: int = BITS) -> np.ndarray:
    """The bits of the twice-filter.  ``keys`` gives arrays in which each document's keys are distinct."""
    segment = 1 << SEGMENT_BITS - 3

    def fill(batches):
        pair = Pair(bits)
        for batch in batches:
            for h in keys(batch):
                pair.add(h)
        at, a, b = [], [], []
        for i in range(0, len(pair.once), segment):
            if (x := pair.once[i : i + segment]).any():
                at.append(i // segment)
                a.append(zlib.compress(x.tobytes(), 1))
                b.append(zlib.compress(pair.twice[i : i + segment].tobytes(), 1))
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(a, pa.binary()), pa.array(b, pa.binary())], ["at", "once", "twice"])

    filled = docs.mapInArrow(fill, "at int, once binary, twice binary")
    # Several tasks' segments meet in a first round of small groups, so that no group grows with the number of tasks.
    salted = filled.withColumn("lot", F.pmod(F.xxhash64("once"), F.lit(8)).cast("int"))

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        once, twice = np.zeros(segment, np.uint8), np.zeros(segment, np.uint8)
        for a, b in zip(pdf["once"], pdf["twice"]):
            x = np.frombuffer(zlib.decompress(a), np.uint8)
            twice |= np.frombuffer(zlib.decompress(b), np.uint8) | (once & x)
            once |= x
        return pd.DataFrame({"at": [pdf["at"].iloc[0]], "once": [zlib.compress(once.tobytes(), 1)], "twice": [zlib.compress(twice.tobytes(), 1)]})

    met = salted.groupBy("at", "lot").applyInPandas(meet, "at int, once binary, twice binary").groupBy("at").applyInPandas(meet, "at int, once binary, twice binary")
    out = np.zeros(1 << bits - 3, np.uint8)
    for r in met.toLocalIterator():  # the size of the filter, however many rows there were
        out[r["at"] * segment : (r["at"] + 1) * segment] = np.frombuffer(zlib.decompress(r["twice"]), np.uint8)
    return out
