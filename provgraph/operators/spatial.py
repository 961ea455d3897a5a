"""Grid index layers, box joins, proximity, nearest neighbours and density."""
from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provgraph.functions.durable import cut

CELL = 800


def _cells(lo: Column, hi: Column, cell: int) -> Column:
    return F.sequence(F.floor(lo / cell), F.floor(hi / cell))


def index(df: DataFrame, *, cell: int = CELL, reach: int = 0, layer: str | None = None) -> DataFrame:
    """One row per (object, grid cell it touches within ``reach``): columns cx, cy and, if named, layer.  Boxes are half-open."""
    out = df.withColumn("cx", F.explode(_cells(F.col("x0") - reach, F.col("x1") - 1 + reach, cell))).withColumn("cy", F.explode(_cells(F.col("y0") - reach, F.col("y1") - 1 + reach, cell)))
    return out if layer is None else out.withColumn("layer", F.lit(layer))


def level_for(df: DataFrame, *, least: int = 100) -> DataFrame:
    """Adds ``level``: the finest grid level (cell side least * 2**level) whose cell is not smaller than the object."""
    side = F.greatest(F.col("x1") - F.col("x0"), F.col("y1") - F.col("y0"), F.lit(1))
    return df.withColumn("level", F.greatest(F.lit(0), F.ceil(F.log2(side / least))).cast("int"))


def _suffixed(df: DataFrame, key: str, suffix: str) -> DataFrame:
    return df.select(*[F.col(c).alias(f"{c}{suffix}") if c in (key, "x0", "y0", "x1", "y1", "area", "cx", "cy", "level") else F.col(c) for c in df.columns])


def shared_area(a: str = "_a", b: str = "_b") -> Column:
    side = lambda lo, hi: F.greatest(F.least(F.col(hi + a), F.col(hi + b)) - F.greatest(F.col(lo + a), F.col(lo + b)), F.lit(0))
    return side("x0", "x1") * side("y0", "y1")


def overlap_join(a: DataFrame, b: DataFrame, *, cell: int = CELL, strategy: str = "grid", key: str = "city") -> DataFrame:
    """Pairs of one ``key`` whose boxes share area; columns of a and b with suffixes _a, _b on key and box, and ``shared``.

    ``grid``: an equi-join on cells; a pair that shares several cells counts only in the cell of its
    intersection's lower corner, so no distinct is needed.  ``levels``: each object sits in the one
    cell size that fits it, and probes every level of the other side (sizes may differ widely).
    ``nested``: every pair of a key's horizontal stripe (``cell`` high) is tested, however far apart along it
    (the baseline); a pair counts in the stripe of its intersection's lower side.  Boxes that only touch share no area; null boxes match nothing.
    """
    names_b = [c for c in b.columns if c in a.columns and c not in (key, "x0", "y0", "x1", "y1", "area")]
    if names_b:
        raise ValueError(f"columns on both sides: {names_b}")
    touch = (F.col("x0_a") < F.col("x1_b")) & (F.col("x0_b") < F.col("x1_a")) & (F.col("y0_a") < F.col("y1_b")) & (F.col("y0_b") < F.col("y1_a"))
    same = F.col(f"{key}_a") == F.col(f"{key}_b")
    if strategy == "nested":
        stripes = lambda df: df.withColumn("cy", F.explode(_cells(F.col("y0"), F.col("y1") - 1, cell)))
        lower = F.floor(F.greatest(F.col("y0_a"), F.col("y0_b")) / cell)
        out = _suffixed(stripes(a), key, "_a").join(_suffixed(stripes(b), key, "_b"), same & (F.col("cy_a") == F.col("cy_b")) & touch & (F.col("cy_a") == lower)).drop("cy_a", "cy_b")
    elif strategy == "grid":
        corner = lambda v: F.floor(F.greatest(F.col(f"{v}_a"), F.col(f"{v}_b")) / cell)
        on = same & (F.col("cx_a") == F.col("cx_b")) & (F.col("cy_a") == F.col("cy_b")) & touch & (F.col("cx_a") == corner("x0")) & (F.col("cy_a") == corner("y0"))
        out = _suffixed(index(a, cell=cell), key, "_a").join(_suffixed(index(b, cell=cell), key, "_b"), on).drop("cx_a", "cy_a", "cx_b", "cy_b")
    elif strategy == "levels":
        return _by_levels(a, b, key, touch, same)
    else:
        raise ValueError(strategy)
    return out.withColumn("shared", shared_area())


def _by_levels(a: DataFrame, b: DataFrame, key: str, touch: Column, same: Column) -> DataFrame:
    left, right = level_for(a), level_for(b)
    levels = [r[0] for r in right.select("level").distinct().orderBy("level").collect()]  # a few dozen at most
    parts = []
    for level in levels:
        side = 100 << level
        own = _suffixed(right.where(F.col("level") == level).withColumns({"cx": F.floor(F.col("x0") / side), "cy": F.floor(F.col("y0") / side)}), key, "_b")
        # An object of this level is at most one cell wide: it starts in a probe's cell or the one before.
        probe = _suffixed(left.withColumn("cx", F.explode(_cells(F.col("x0") - side, F.col("x1") - 1, side))).withColumn("cy", F.explode(_cells(F.col("y0") - side, F.col("y1") - 1, side))), key, "_a")
        parts.append(probe.join(own, same & (F.col("cx_a") == F.col("cx_b")) & (F.col("cy_a") == F.col("cy_b")) & touch).drop("cx_a", "cy_a", "cx_b", "cy_b", "level_a", "level_b"))
    if not parts:
        return overlap_join(a, b, strategy="grid", key=key)
    return reduce(DataFrame.unionByName, parts).withColumn("shared", shared_area())


def window(df: DataFrame, x0: int, y0: int, x1: int, y1: int) -> DataFrame:
    """Objects that share area with a half-open box: plain comparisons, pushed to the scan."""
    return df.where((F.col("x0") < x1) & (F.col("x1") > x0) & (F.col("y0") < y1) & (F.col("y1") > y0))


def vertical_overlap(base_a: Column, height_a: Column, base_b: Column, height_b: Column) -> Column:
    """The height that two solids over their base elevations have in common; 0 where one stands above the other."""
    return F.greatest(F.least(base_a + height_a, base_b + height_b) - F.greatest(base_a, base_b), F.lit(0))


def gap2(a: str = "_a", b: str = "_b") -> Column:
    """Squared distance between two boxes; 0 where they touch."""
    side = lambda lo, hi: F.greatest(F.col(lo + b) - F.col(hi + a), F.col(lo + a) - F.col(hi + b), F.lit(0))
    dx, dy = side("x0", "x1"), side("y0", "y1")
    return dx * dx + dy * dy


def as_boxes(points: DataFrame, x: str = "x", y: str = "y") -> DataFrame:
    return points.withColumns({"x0": F.col(x), "y0": F.col(y), "x1": F.col(x), "y1": F.col(y)}).drop(x, y)


def centres(df: DataFrame) -> DataFrame:
    """``df`` with each box shrunk to its centre."""
    x, y = (F.col("x0") + F.col("x1")) / 2, (F.col("y0") + F.col("y1")) / 2
    return df.withColumns({"x0": x, "x1": x, "y0": y, "y1": y})


def within(a: DataFrame, b: DataFrame, d: int, *, inclusive: bool = True, key: str = "city", metric: str = "box") -> DataFrame:
    """Pairs of one key at most (or, not inclusive, less than) ``d`` apart, with dist2; no pair twice.

    ``box``: the distance between the boxes, 0 where they touch; ``centre``: between their centres.
    """
    if metric not in ("box", "centre"):
        raise ValueError(metric)
    if metric == "centre":
        a, b = centres(a), centres(b)
    cell = max(CELL, d)
    left = _suffixed(a.withColumns({"cx": F.explode(_cells(F.col("x0") - d, F.col("x1") + d, cell))}).withColumn("cy", F.explode(_cells(F.col("y0") - d, F.col("y1") + d, cell))), key, "_a")
    right = _suffixed(b.withColumn("cx", F.explode(_cells(F.col("x0"), F.col("x1"), cell))).withColumn("cy", F.explode(_cells(F.col("y0"), F.col("y1"), cell))), key, "_b")
    corner = lambda v: F.floor(F.greatest(F.col(f"{v}_a") - d, F.col(f"{v}_b")) / cell)
    near = gap2() <= d * d if inclusive else gap2() < d * d
    on = (F.col(f"{key}_a") == F.col(f"{key}_b")) & (F.col("cx_a") == F.col("cx_b")) & (F.col("cy_a") == F.col("cy_b")) & (F.col("cx_a") == corner("x0")) & (F.col("cy_a") == corner("y0")) & near
    return left.join(right, on).withColumn("dist2", gap2()).drop("cx_a", "cy_a", "cx_b", "cy_b")


def knn(a: DataFrame, b: DataFrame, k: int, *, a_id: str, b_id: str, cell: int = CELL, max_rounds: int = 12, key: str = "city") -> DataFrame:
    """(a_id, b_id, dist2, rank): the ``k`` nearest of b for each of a, ties to the smaller id.

    Rounds search four times as far as the last one; a row is final once it has k results no farther than that
    distance, or the whole of its key has been searched.  Fewer than k objects: all of them.
    """
    todo, reach, done = a, cell, []
    extent = a.select(key, "x0", "y0", "x1", "y1").union(b.select(key, "x0", "y0", "x1", "y1")).agg(F.min("x0"), F.min("y0"), F.max("x1"), F.max("y1")).first()
    span = max(extent[2] - extent[0], extent[3] - extent[1]) * 2 if extent[0] is not None else 0
    order = Window.partitionBy(a_id).orderBy("dist2", b_id)
    for _ in range(max_rounds):
        last = reach >= span
        near = within(todo, b, reach, key=key).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select(a_id, b_id, "dist2", "rank")
        if last:
            done.append(near)
            break
        near = cut(near)
        full = near.groupBy(a_id).agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") >= k).select(F.col(a_id).alias("_a"))
        done.append(near.join(full, F.col(a_id) == F.col("_a"), "left_semi"))
        todo = cut(todo.join(full, F.col(a_id) == F.col("_a"), "left_anti"))
        if todo.isEmpty():
            break
        reach *= 4
    return reduce(DataFrame.union, done).select(a_id, b_id, "dist2", F.col("rank").cast("long").alias("rank"))


def density(df: DataFrame, cell: int = 3200, key: str = "city") -> DataFrame:
    """Objects and their area per cell of their lower corner."""
    return df.groupBy(key, F.floor(F.col("x0") / cell).alias("cx"), F.floor(F.col("y0") / cell).alias("cy")).agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("x1") - F.col("x0")) * (F.col("y1") - F.col("y0"))).alias("built"))
