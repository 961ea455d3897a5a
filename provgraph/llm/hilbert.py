"""Shards cut from a Hilbert curve over several metadata dimensions, with DataFrame functions only.

Each dimension is put into equal-share bins; the bins' curve index orders the rows, so that a shard
is a compact region and a reader can skip shards by every dimension's smallest and largest value.
"""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provgraph.functions.columns import column, hashable, packed, unpacked
from provgraph.functions.durable import cut

BITS = 4
SHARDS = 24
SUB_BUCKETS = 1024
#: Curve cells that share one prefix sum task.
CELLS_A_TASK = 64
#: The curve is looked up in a broadcast table of up to 2**so many cells, and worked out row by row beyond.
TABLE_BITS = 16
#: Ranges of values in which strings are counted in order.
RANGES = 64


def as_measure(column: Column, kind: str) -> Column:
    """What a dimension is compared by: strings as they are, all else as a number; null below everything."""
    if kind == "string":
        return column
    number = column.cast("double")
    return F.coalesce(F.when(F.isnan(number), F.lit(float("inf"))).otherwise(number), F.lit(float("-inf")))


def string_edges(df: DataFrame, value: Column, at: list[float]) -> list[str]:
    """The values at the shares ``at`` of all rows in order of ``value`` (nulls left out), without repeats; the driver gets only these.

    Values are counted first, so a frequent one is one row; counts add up inside ranges of values, whose totals
    (a row a range) are added to them.
    """
    counts = df.groupBy(value.alias("v")).agg(F.count(F.lit(1)).alias("n")).where("v is not null")
    ranges = cut(counts.repartitionByRange(RANGES, "v").withColumn("part", F.spark_partition_id()))
    totals, before, n = {r["part"]: r["n"] for r in ranges.groupBy("part").agg(F.sum("n").alias("n")).collect()}, {}, 0
    for part in sorted(totals):
        before[part], n = n, n + totals[part]
    if not n:
        return []
    start = F.element_at(F.create_map(*[F.lit(x) for kv in before.items() for x in kv]), F.col("part"))
    upto = ranges.withColumn("upto", F.sum("n").over(Window.partitionBy("part").orderBy("v")) + start)
    row = upto.agg(*[F.min(F.when(F.col("upto") > int(n * x), F.col("v"))).alias(f"e{i}") for i, x in enumerate(at)]).first()
    return sorted(set(row), key=lambda v: v.encode())


def bin_edges(df: DataFrame, dims: dict[str, Column], strings: set[str], bits: int) -> dict[str, list]:
    """Per dimension the inner edges of 2**bits bins of near equal share; the driver gets only these.

    Numbers by approximate percentiles of all rows, whole strings by exact counts of all rows.
    """
    at = [i / (1 << bits) for i in range(1, 1 << bits)]
    numbers = {n: c for n, c in dims.items() if n not in strings}
    out: dict[str, list] = {}
    if numbers:
        row = df.agg(*[F.percentile_approx(F.greatest(F.least(c, F.lit(1e300)), F.lit(-1e300)), at, 10_000).alias(n) for n, c in numbers.items()]).first()
        out = {n: sorted(set(row[n] or [])) for n in numbers}
    return out | {n: string_edges(df, dims[n], at) for n in sorted(strings)}


def with_curve(df: DataFrame, bins: list[Column], bits: int, out: str = "curve") -> DataFrame:
    """Adds the Hilbert index (a long) of non-negative bins of ``bits`` bits each.

    Each turn of the curve is a projection of its own over plain integers, so that the generated code
    stays as long as the number of turns and no expression is worked out twice.
    """
    ax = [f"_x{i}" for i in range(len(bins))]
    df = df.withColumns({x: b.cast("long") for x, b in zip(ax, bins)})
    for q in (1 << k for k in range(bits - 1, 0, -1)):
        for i, x in enumerate(ax):
            inside = F.col(x).bitwiseAND(F.lit(q)) != 0
            if i == 0:
                df = df.withColumn(x, F.when(inside, F.col(x).bitwiseXOR(F.lit(q - 1))).otherwise(F.col(x)))
                continue
            df = df.withColumn("_t", F.when(inside, F.lit(q - 1)).otherwise(F.col(ax[0]).bitwiseXOR(F.col(x)).bitwiseAND(F.lit(q - 1))))
            df = df.withColumns({x: F.when(inside, F.col(x)).otherwise(F.col(x).bitwiseXOR(F.col("_t"))), ax[0]: F.col(ax[0]).bitwiseXOR(F.col("_t"))})
    for before, x in zip(ax, ax[1:]):  # Gray code
        df = df.withColumn(x, F.col(x).bitwiseXOR(F.col(before)))
    df = df.withColumn("_t", F.lit(0).cast("long"))
    for q in (1 << k for k in range(bits - 1, 0, -1)):
        df = df.withColumn("_t", F.when(F.col(ax[-1]).bitwiseAND(F.lit(q)) != 0, F.col("_t").bitwiseXOR(F.lit(q - 1))).otherwise(F.col("_t")))
    df = df.withColumns({x: F.col(x).bitwiseXOR(F.col("_t")) for x in ax})
    index = F.lit(0).cast("long")
    for k in range(bits - 1, -1, -1):
        for x in ax:
            index = index * 2 + F.shiftright(x, k).bitwiseAND(F.lit(1))
    return df.withColumn(out, index).drop("_t", *ax)


def shard(df: DataFrame, dims: list[str], *, shards: int = SHARDS, bits: int = BITS, spread: list[Column] | None = None, size: Column | None = None, law: str = "rows") -> DataFrame:
    """Adds curve (long), place (0-based along the curve), shard (int) and slot (0-based in the shard).

    Law ``rows``: counts of shards differ by at most one.  Law ``bytes``: shards are cut where the
    running ``size`` passes each equal share, so sizes differ by at most about one row.
    Rows of one curve cell follow a hash of ``spread`` (all columns by default); a cell may hold any share
    of the rows, for it is dealt over hash buckets before it is numbered.  Nulls are in the lowest bin;
    equal rows get places side by side; an empty table stays empty; columns of the same name as an added
    one are replaced by it.
    """
    if law not in ("rows", "bytes"):
        raise ValueError(f"law {law!r}")
    kinds = dict(df.dtypes)
    names = [f"m{i}" for i in range(len(dims))]
    measures = {n: as_measure(column(d), kinds[d]) for n, d in zip(names, dims)}
    strings = {n for n, d in zip(names, dims) if kinds[d] == "string"}
    edges = bin_edges(df, measures, strings, bits)
    bins = {n: sum((F.when(m > e, 1).otherwise(0) for e in edges[n]), F.lit(0)) for n, m in measures.items()}
    total = bits * len(dims)
    rows = packed(df, **bins, w=(size if size is not None else F.lit(1)).cast("long"), s=F.xxhash64(*(spread or hashable(df))), tie=F.xxhash64(*hashable(df)))
    if total <= TABLE_BITS:  # the curve of every cell, cut off so that no plan holds its formula
        codes = df.sparkSession.range(1 << total)
        part = [F.shiftright("id", bits * i).bitwiseAND(F.lit((1 << bits) - 1)) for i in range(len(dims))]
        codes = cut(with_curve(codes, part, bits)).select(F.col("id").alias("code2"), "curve")
        code = sum((F.col(n).cast("long") * (1 << bits * i) for i, n in enumerate(names)), F.lit(0).cast("long"))
        rows = rows.withColumn("code", code).join(F.broadcast(codes), F.col("code") == F.col("code2")).drop("code", "code2")
    else:
        rows = with_curve(rows, [F.col(n) for n in names], bits)
    cells_a_task = max(CELLS_A_TASK, 1 << max(0, total - 12))  # at most 4,096 such groups of cells
    rows = rows.drop(*names).withColumns({"hi": F.floor(F.col("curve") / cells_a_task), "sub": F.pmod("s", F.lit(SUB_BUCKETS)).cast("int")})
    cells = rows.groupBy("hi", "curve", "sub").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("b"))
    inside = Window.partitionBy("hi").orderBy("curve", "sub")
    cells = cells.select(F.col("hi").alias("hi2"), F.col("curve").alias("curve2"), F.col("sub").alias("sub2"), (F.sum("n").over(inside) - F.col("n")).alias("n0"), (F.sum("b").over(inside) - F.col("b")).alias("b0"))
    # At most 4,096 rows: a bounded table for one task and for broadcast.
    whole = Window.orderBy("hi")
    tops = rows.groupBy("hi").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("b"))
    every = whole.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    tops = tops.select(F.col("hi").alias("top"), (F.sum("n").over(whole) - F.col("n")).alias("n1"), (F.sum("b").over(whole) - F.col("b")).alias("b1"), F.sum("n").over(every).alias("all_n"), F.sum("b").over(every).alias("all_b"))
    own = Window.partitionBy("hi", "curve", "sub").orderBy("s", "tie")
    numbered = rows.withColumns({"r": F.row_number().over(own) - 1, "u": F.sum("w").over(own.rowsBetween(Window.unboundedPreceding, 0)) - F.col("w")})
    placed = numbered.join(cells, (F.col("hi") == F.col("hi2")) & (F.col("curve") == F.col("curve2")) & (F.col("sub") == F.col("sub2"))).join(F.broadcast(tops), F.col("hi") == F.col("top"))
    placed = placed.withColumn("place", (F.col("n1") + F.col("n0") + F.col("r")).cast("long"))
    if law == "rows":
        placed = placed.withColumn("shard", F.expr(f"place * {shards} div all_n").cast("int"))
        slot = F.expr(f"place - (shard * all_n + {shards - 1}) div {shards}")
    else:
        placed = placed.withColumn("shard", F.least(F.expr(f"(b1 + b0 + u) * {shards} div greatest(all_b, 1L)"), F.lit(shards - 1)).cast("int"))
        firsts = placed.groupBy(F.col("shard").alias("shard2")).agg(F.min("place").alias("first"))
        placed = placed.join(F.broadcast(firsts), F.col("shard") == F.col("shard2"))  # a row a shard
        slot = F.col("place") - F.col("first")
    return unpacked(placed, df.columns, curve=F.col("curve"), place=F.col("place"), shard=F.col("shard"), slot=slot.cast("long"))


def write_shards(sharded: DataFrame, path: str) -> None:
    """A folder per shard, rows in curve order: file statistics then prune on every dimension."""
    n = sharded.agg(F.max("shard")).first()[0]
    sharded.repartition(int(n or 0) + 1, "shard").sortWithinPartitions("shard", "slot").write.mode("overwrite").partitionBy("shard").parquet(path)


def manifest(sharded: DataFrame, dims: list[str]) -> DataFrame:
    """Per shard its rows and each dimension's range, for pruning."""
    return sharded.groupBy("shard").agg(F.count(F.lit(1)).alias("rows"), *[f(d).alias(f"{n}_{d}") for d in dims for n, f in (("min", F.min), ("max", F.max))])


def digest(docs: DataFrame, **options) -> DataFrame:
    rows = docs.select("doc_id", "source", "lang", "n_chars", (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long").alias("size"), F.coalesce(F.crc32(F.encode("text", "utf-8")), F.lit(0)).cast("long").alias("text_crc32"))
    out = shard(rows, ["source", "lang", "n_chars"], spread=[F.col("text_crc32"), F.col("doc_id")], size=F.col("size"), **options)
    return out.select("doc_id", "size", "text_crc32", F.lit(options.get("law", "rows")).alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")
