"""Polygon measures, exact clipping by fan triangles, and a transverse Mercator projection as column expressions."""
from __future__ import annotations

from math import sqrt

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


def _twice_area(r: Column) -> Column:
    n = F.size(r)
    after = F.concat(F.slice(r, F.lit(2), n), F.slice(r, F.lit(1), F.least(n, F.lit(1))))
    return F.aggregate(F.zip_with(r, after, lambda p, q: p["x"] * q["y"] - q["x"] * p["y"]), F.lit(0.0), lambda a, v: a + v)


def ring_area(r: Column) -> Column:
    """Area inside one ring of (x, y), whatever its direction; open or closed."""
    return F.abs(_twice_area(r)) / 2


def polygon_area(rings: Column) -> Column:
    """The first ring's area less the others' (holes); null for null, 0 for none."""
    areas = F.transform(rings, ring_area)
    return F.when(F.size(rings) > 0, 2 * F.element_at(areas, 1) - F.aggregate(areas, F.lit(0.0), lambda a, v: a + v)).when(rings.isNotNull(), 0.0)


def polygon_box(rings: Column) -> dict[str, Column]:
    xs, ys = F.transform(rings[0], lambda p: p["x"]), F.transform(rings[0], lambda p: p["y"])
    return {"x0": F.array_min(xs), "y0": F.array_min(ys), "x1": F.array_max(xs), "y1": F.array_max(ys)}


def _area(poly) -> float:
    return sum(p[0] * q[1] - q[0] * p[1] for p, q in zip(poly, poly[1:] + poly[:1])) / 2 if len(poly) > 2 else 0.0


def _triangles(rings, apex):
    """Signed triangles whose indicator functions add up to the polygon's."""
    for i, ring in enumerate(rings):
        pts = [(float(p["x"]), float(p["y"])) for p in ring]
        whole = _area(pts)
        turn = (1 if whole >= 0 else -1) * (1 if i == 0 else -1)
        for p, q in zip(pts, pts[1:] + pts[:1]):
            t = _area([apex, p, q])
            if t:
                yield turn * (1 if t > 0 else -1), [apex, p, q] if t > 0 else [apex, q, p]


def _clipped(poly: np.ndarray, count: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Convex polygons (n, corners, 2) with their numbers of corners, each cut to the left of its own line a -> b."""
    n, m, _ = poly.shape
    at = np.arange(m)[None, :]
    live = at < count[:, None]
    after = np.where(at + 1 < count[:, None], at + 1, 0)
    nxt = np.take_along_axis(poly, after[:, :, None], axis=1)
    side = lambda p: (b - a)[:, None, 0] * (p[:, :, 1] - a[:, None, 1]) - (b - a)[:, None, 1] * (p[:, :, 0] - a[:, None, 0])
    s, t = side(poly), side(nxt)
    crosses = live & (((s > 0) & (t < 0)) | ((s < 0) & (t > 0)))
    k = np.divide(s, s - t, out=np.zeros_like(s), where=crosses)
    points = np.stack([poly, poly + k[:, :, None] * (nxt - poly)], axis=2).reshape(n, 2 * m, 2)
    kept = np.stack([live & (s >= 0), crosses], axis=2).reshape(n, 2 * m)
    order = np.argsort(~kept, axis=1, kind="stable")[:, : m + 1]
    return np.take_along_axis(points, order[:, :, None], axis=1), kept.sum(axis=1)


def overlaps_of(pairs: list[tuple]) -> np.ndarray:
    """Shared areas of pairs of simple polygons with holes; null or empty ones share none."""
    sign, left, right, whose = [], [], [], []
    for i, (a, b) in enumerate(pairs):
        if a is None or b is None or not len(a) or not len(b):
            continue
        apex = (float(a[0][0]["x"]), float(a[0][0]["y"]))
        other = list(_triangles(b, apex))
        for s, t in _triangles(a, apex):
            for u, v in other:
                sign.append(s * u)
                left.append(t)
                right.append(v)
                whose.append(i)
    out = np.zeros(len(pairs))
    for lo in range(0, len(sign), 65_536):
        poly, cut = np.array(left[lo : lo + 65_536]), np.array(right[lo : lo + 65_536])
        count = np.full(len(poly), 3)
        for i in range(3):
            poly, count = _clipped(poly, count, cut[:, i], cut[:, (i + 1) % 3])
        at = np.arange(poly.shape[1])[None, :]
        nxt = np.take_along_axis(poly, np.where(at + 1 < count[:, None], at + 1, 0)[:, :, None], axis=1)
        twice = np.where(at < count[:, None], poly[:, :, 0] * nxt[:, :, 1] - nxt[:, :, 0] * poly[:, :, 1], 0).sum(axis=1)
        np.add.at(out, whose[lo : lo + 65_536], np.array(sign[lo : lo + 65_536]) * twice / 2)
    return np.maximum(out, 0)


def overlap_of(a, b) -> float:
    """Shared area of two simple polygons with holes."""
    return float(overlaps_of([(a, b)])[0])


def polygon_overlap_area(a: Column | str, b: Column | str) -> Column:
    """Shared area of two columns of rings, in Arrow batches; null or empty rings share none."""

    @F.pandas_udf("double")
    def clipped(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series(np.concatenate([overlaps_of(list(zip(a[i : i + 1000], b[i : i + 1000]))) for i in range(0, len(a), 1000)] or [np.empty(0)]))

    return clipped(a, b)


def polygon_centroid(rings: Column) -> Column:
    """(x, y) of the area's centre, holes taken out; null without area."""

    def moments(r: Column) -> Column:
        n = F.size(r)
        after = F.concat(F.slice(r, F.lit(2), n), F.slice(r, F.lit(1), F.least(n, F.lit(1))))
        cross = lambda p, q: p["x"] * q["y"] - q["x"] * p["y"]
        parts = F.zip_with(r, after, lambda p, q: F.struct(cross(p, q).cast("double").alias("a"), ((p["x"] + q["x"]) * cross(p, q)).cast("double").alias("x"), ((p["y"] + q["y"]) * cross(p, q)).cast("double").alias("y")))
        zero = F.struct(*[F.lit(0.0).alias(k) for k in "axy"])
        got = F.aggregate(parts, zero, lambda s, v: F.struct(*[(s[k] + v[k]).alias(k) for k in "axy"]))
        return F.struct(F.abs(got["a"]).alias("a"), (got["x"] * F.signum(got["a"])).alias("x"), (got["y"] * F.signum(got["a"])).alias("y"))

    each = F.transform(rings, moments)
    total = lambda k: 2 * F.element_at(each, 1)[k] - F.aggregate(each, F.lit(0.0), lambda s, m: s + m[k])
    area = F.when(F.size(rings) > 0, total("a"))
    return F.when(area > 0, F.struct((total("x") / (3 * area)).alias("x"), (total("y") / (3 * area)).alias("y")))


def reproject_tm(lon: Column, lat: Column, *, lon0: float, k0: float = 0.9996, fe: float = 500_000.0, fn: float = 0.0, a: float = 6378137.0, f: float = 1 / 298.257223563) -> tuple[Column, Column]:
    """Easting and northing of the transverse Mercator projection, by the series in the third flattening to the fourth order."""
    n = f / (2 - f)
    big = a / (1 + n) * (1 + n**2 / 4 + n**4 / 64)
    alpha = [n / 2 - 2 * n**2 / 3 + 5 * n**3 / 16 + 41 * n**4 / 180, 13 * n**2 / 48 - 3 * n**3 / 5 + 557 * n**4 / 1440, 61 * n**3 / 240 - 103 * n**4 / 140, 49561 * n**4 / 161280]
    c = 2 * sqrt(n) / (1 + n)
    phi, lam = F.radians(lat), F.radians(lon - lon0)
    s = F.sin(phi)
    t = F.sinh(F.atanh(s) - c * F.atanh(c * s))
    xi, eta = F.atan2(t, F.cos(lam)), F.atanh(F.sin(lam) / F.sqrt(1 + t * t))
    east, north = eta, xi
    for j, x in enumerate(alpha, 1):
        east = east + x * F.cos(2 * j * xi) * F.sinh(2 * j * eta)
        north = north + x * F.sin(2 * j * xi) * F.cosh(2 * j * eta)
    return fe + k0 * big * east, fn + k0 * big * north
