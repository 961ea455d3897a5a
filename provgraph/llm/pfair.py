"""Mixing sources to target weights by Pfair scheduling.

Block j (from 0) of a source with weight w may run from slot floor(j / w) and must run before slot
ceil((j + 1) / w); of the released blocks the one with the earliest deadline goes next.  At every slot
each source that still has blocks is then less than one block away from its weight.

Weights are exact fractions: whole numbers in the targets' ratios.  With their sum D the schedule
repeats every D slots, so the driver works out one period whatever the number of rows, and a block's
slot is arithmetic on its number.  A source that has run out leaves its slots empty, so the others keep
their schedule, and their ratios, for good; no row is dropped or repeated.
"""
from __future__ import annotations

import heapq
from fractions import Fraction
from math import gcd, lcm

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from provgraph.functions.columns import column, hashable, packed, unpacked
from provgraph.functions.ranking import position_within

BLOCK_ROWS = 16
#: Default targets are multiples of one in so many.
UNITS = 10_000
#: The longest period: the bound of the table that is broadcast (one whole number a slot).
MOST_SLOTS = 1 << 20


def whole_weights(weights: dict[str, float | str | Fraction]) -> dict[str, int]:
    """The smallest whole numbers in exactly the ratios of ``weights``, decimals taken as they print."""
    exact = {s: Fraction(str(w)) for s, w in weights.items()}
    if any(w <= 0 for w in exact.values()):
        raise ValueError("weights must be positive")
    scale = lcm(*(w.denominator for w in exact.values()))
    whole = {s: int(w * scale) for s, w in exact.items()}
    least = gcd(*whole.values())
    whole = {s: w // least for s, w in whole.items()}
    if sum(whole.values()) > MOST_SLOTS:
        raise ValueError(f"weights need a period of {sum(whole.values())} slots; give them fewer digits (at most {MOST_SLOTS} slots)")
    return whole


def root_weights(rows: dict[str, int], units: int = UNITS) -> dict[str, int]:
    """Targets for want of any: the square root of each source's number of rows, which gives small sources more than their share."""
    root = {s: n**0.5 for s, n in rows.items()}
    total = sum(root.values())
    return whole_weights({s: max(1, round(units * r / total)) for s, r in root.items()})


def period(shares: dict[str, int]) -> dict[str, list[int]]:
    """One period of the earliest-deadline schedule: the slots of each source's blocks."""
    slots = sum(shares.values())
    coming = [(0, -(-slots // a), s, 1) for s, a in shares.items()]
    heapq.heapify(coming)
    ready: list[tuple[int, str, int]] = []
    out: dict[str, list[int]] = {s: [] for s in shares}
    for t in range(slots):
        while coming and coming[0][0] <= t:
            _, d, s, j = heapq.heappop(coming)
            heapq.heappush(ready, (d, s, j))
        d, s, j = heapq.heappop(ready)
        assert t < d
        out[s].append(t)
        if j < shares[s]:
            heapq.heappush(coming, (j * slots // shares[s], -(-(j + 1) * slots // shares[s]), s, j + 1))
    return out


def _digest(ids: list[Column]) -> Column:
    """32 hex digits that tell rows apart by ``ids``."""
    text = [F.coalesce(i.cast("string"), F.lit("")) for i in ids]
    return F.md5(F.concat_ws("\x1f", *text) if len(text) > 1 else text[0])


def _placed(docs: DataFrame, weights, other, source: str, block_rows: int, spread: list[str] | None) -> tuple[DataFrame, dict[str, Column]]:
    """The packed rows with what the schedule says of them, and the columns that it adds."""
    lot = F.coalesce(F.concat(F.lit("s:"), column(source).cast("string")), F.lit("null"))
    rows = {r["lot"]: r["n"] for r in docs.groupBy(lot.alias("lot")).agg(F.count(F.lit(1)).alias("n")).collect()}  # a row a source
    if weights:
        given = {f"s:{k}" if k is not None else "null": Fraction(str(v)) for k, v in weights.items()}
        rest = min(given.values()) if other is None else Fraction(str(other))
        share = whole_weights({s: given.get(s, rest) for s in rows}) if rows else {}
    else:
        share = root_weights(rows) if rows else {}
    size = sum(share.values())
    plan = docs.sparkSession.createDataFrame([(s, share[s], at) for s, at in period(share).items()], "of string, share long, places array<int>")
    keyed = packed(docs, lot=lot, digest=_digest([column(c) for c in (spread or docs.columns)]), tie=F.xxhash64(*hashable(docs)))
    numbered = position_within(keyed, F.col("lot"), [F.col("digest"), F.col("tie")], F.conv(F.substring("digest", 1, 3), 16, 10).cast("int"), "at")
    numbered = numbered.withColumn("block", F.expr(f"at div {block_rows}"))
    joined = numbered.join(F.broadcast(plan), F.col("lot") == F.col("of"))  # at most MOST_SLOTS numbers
    return joined, {
        "block": F.col("block"),
        "pos": (F.col("at") % block_rows).cast("int"),
        "release": F.expr(f"block * {size}L div share"),
        "deadline": F.expr(f"((block + 1) * {size}L + share - 1) div share"),
        "slot": F.expr("block div share") * F.lit(size).cast("long") + F.get("places", (F.col("block") % F.col("share")).cast("int")),
    }


def mix(docs: DataFrame, weights: dict[str | None, float | str | Fraction] | None = None, *, other: float | str | Fraction | None = None, source: str = "source", block_rows: int = BLOCK_ROWS, spread: list[str] | None = None) -> DataFrame:
    """``docs`` with block (number in its source), pos (row in the block), release, deadline and slot.

    ``weights``: by source (None for null); a source that isn't listed has ``other``, or else the smallest
    weight given; without any, see ``root_weights``.  Only sources with rows count, and every one of them
    has its own schedule.  Slots increase along the mix and are unique to a block.  Rows of a source follow
    a digest of the columns ``spread`` (all by default), equal rows stand side by side.  Every row stays;
    an empty table stays empty; columns of the same name as an added one are replaced by it.
    """
    rows, added = _placed(docs, weights, other, source, block_rows, spread)
    return unpacked(rows, docs.columns, **added)


def mixed(docs: DataFrame, weights: dict[str | None, float | str | Fraction] | None = None, *, other: float | str | Fraction | None = None, source: str = "source", block_rows: int = BLOCK_ROWS, spread: list[str] | None = None) -> DataFrame:
    """``docs`` in the order of the mix, all of its columns and no others."""
    rows, added = _placed(docs, weights, other, source, block_rows, spread)
    return unpacked(rows.orderBy(added["slot"], added["pos"]), docs.columns)
