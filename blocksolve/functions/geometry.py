"""Scan geometry: rays, grids, exact ray tracing and shadows of blocks, as expressions over generated rows.

The grid is centred on the origin with unit cells. A ray is a row with src and dst points; its entries are the
lengths of its parts inside the cells, found from the places where it crosses the grid's planes.
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksolve.functions.hashing import uniform_of

SHORT = 1e-9


def _points(df: DataFrame, src: list[Column], dst: list[Column]) -> DataFrame:
    point = lambda p: F.struct(*[c.cast("double").alias(n) for c, n in zip(p, "xyz", strict=True)])
    return df.select("row_id", "rb", "view", "det", "sub", point(src).alias("src"), point(dst).alias("dst"))


def _grid_of_rays(spark: SparkSession, views: int, dets: int, subs: int, read: DataFrame | None = None) -> DataFrame:
    """Every cell of every view, or the rays of ``read`` (row_id, view, det)."""
    if read is None:
        df = spark.range(views * dets).withColumnRenamed("id", "row_id")
        df = df.withColumns({"view": F.floor(F.col("row_id") / dets).cast("int"), "det": F.pmod("row_id", F.lit(dets)).cast("int")})
    else:
        df = read.select("row_id", "view", "det")
    df = df.withColumn("sub", F.floor(F.col("det") * subs / dets).cast("int"))
    return df.withColumn("rb", (F.col("view") * subs + F.col("sub")).cast("int"))


def fan_rays(spark: SparkSession, views: int = 360, dets: int = 187, radius: float = 115.0, pitch: float = 1.0, subs: int = 2, phase: float = 1e-3, read: DataFrame | None = None) -> DataFrame:
    """Source and detector line on a circle, opposite each other. ``phase`` turns the circle off the grid's axes. ``read``: the rays that were read, if not all."""
    df = _grid_of_rays(spark, views, dets, subs, read)
    phi = F.col("view") * (2 * math.pi / views) + phase
    u = (F.col("det") - (dets - 1) / 2) * pitch
    c, s, zero = F.cos(phi), F.sin(phi), F.lit(0.0)
    return _points(df, [radius * c, radius * s, zero], [-radius * c - u * s, -radius * s + u * c, zero])


def parallel_rays(spark: SparkSession, views: int, dets: int, radius: float, pitch: float = 1.0, subs: int = 1, phase: float = 1e-3, read: DataFrame | None = None) -> DataFrame:
    df = _grid_of_rays(spark, views, dets, subs, read)
    phi = F.col("view") * (math.pi / views) + phase
    u = (F.col("det") - (dets - 1) / 2) * pitch
    c, s, zero = F.cos(phi), F.sin(phi), F.lit(0.0)
    return _points(df, [radius * c - u * s, radius * s + u * c, zero], [-radius * c - u * s, -radius * s + u * c, zero])


def cone_frames(views: int, seed: int) -> list[tuple]:
    """Per view: unit direction of the source and two in-plane axes, from two seeded angles."""
    out = []
    for v in range(views):
        polar, azimuth = math.pi * uniform_of(seed, v, "polar"), 2 * math.pi * uniform_of(seed, v, "azimuth")
        n = (math.sin(polar) * math.cos(azimuth), math.sin(polar) * math.sin(azimuth), math.cos(polar))
        up = (0.0, 0.0, 1.0) if abs(n[2]) < 0.9 else (1.0, 0.0, 0.0)
        a = (up[1] * n[2] - up[2] * n[1], up[2] * n[0] - up[0] * n[2], up[0] * n[1] - up[1] * n[0])
        size = math.sqrt(sum(x * x for x in a))
        a = tuple(x / size for x in a)
        b = (n[1] * a[2] - n[2] * a[1], n[2] * a[0] - n[0] * a[2], n[0] * a[1] - n[1] * a[0])
        out.append((v, *n, *a, *b))
    return out


def cone_rays(spark: SparkSession, views: int = 48, side: int = 26, pitch: float = 1.0, radius: float = 66.0, distance: float = 132.0, seed: int = 0, parts: int = 1, read: DataFrame | None = None) -> DataFrame:
    """Random source directions at a fixed radius; the square detector (side x side cells) stays perpendicular. ``parts`` cuts each of its sides. ``read``: as in ``fan_rays``."""
    frames = spark.createDataFrame(cone_frames(views, seed), "view int, nx double, ny double, nz double, ax double, ay double, az double, bx double, by double, bz double")
    df = _grid_of_rays(spark, views, side * side, 1, read).withColumns({"i": F.floor(F.col("det") / side), "j": F.pmod("det", F.lit(side))})
    df = df.withColumn("sub", (F.floor(F.col("i") * parts / side) * parts + F.floor(F.col("j") * parts / side)).cast("int"))
    df = df.withColumn("rb", (F.col("view") * (parts * parts) + F.col("sub")).cast("int")).join(F.broadcast(frames), "view")
    u, w = (F.col("i") - (side - 1) / 2) * pitch, (F.col("j") - (side - 1) / 2) * pitch
    away = radius - distance
    dst = [away * F.col(f"n{k}") + u * F.col(f"a{k}") + w * F.col(f"b{k}") for k in "xyz"]
    return _points(df, [radius * F.col(f"n{k}") for k in "xyz"], dst)


def cells(spark: SparkSession, shape: tuple[int, ...], parts: tuple[int, ...]) -> DataFrame:
    """col_id, ix, iy, iz, cb of a grid cut into cuboids."""
    n = [*shape, *[1] * (3 - len(shape))]
    p = [*parts, *[1] * (3 - len(parts))]
    df = spark.range(n[0] * n[1] * n[2]).withColumnRenamed("id", "col_id")
    df = df.withColumns({"ix": F.pmod("col_id", F.lit(n[0])).cast("int"), "iy": F.pmod(F.floor(F.col("col_id") / n[0]), F.lit(n[1])).cast("int"), "iz": F.floor(F.col("col_id") / (n[0] * n[1])).cast("int")})
    part = lambda c, k: F.floor(F.col(c) * p[k] / n[k])
    return df.withColumn("cb", ((part("iz", 2) * p[1] + part("iy", 1)) * p[0] + part("ix", 0)).cast("int"))


def cuboids(shape: tuple[int, ...], parts: tuple[int, ...]) -> list[tuple]:
    """(cb, x0, x1, y0, y1, z0, z1) of the blocks, as ``cells`` cuts them."""
    n = [*shape, *[1] * (3 - len(shape))]
    p = [*parts, *[1] * (3 - len(parts))]
    edge = lambda k, i: -(-i * n[k] // p[k]) - n[k] / 2
    return [
        ((c * p[1] + b) * p[0] + a, edge(0, a), edge(0, a + 1), edge(1, b), edge(1, b + 1), edge(2, c), edge(2, c + 1))
        for c in range(p[2]) for b in range(p[1]) for a in range(p[0])
    ]


def trace(rays: DataFrame, shape: tuple[int, ...], box: tuple | None = None) -> DataFrame:
    """rb, row_id, view, sub, col_id, val: lengths of every ray in every cell it meets, above SHORT.

    ``box`` = (x0, x1, y0, y1, z0, z1) restricts tracing to a block. Grids of two dimensions lie in the plane z = 0.
    """
    axes = "xyz"[: len(shape)]
    n = dict(zip(axes, shape, strict=True))
    df = rays
    for a in axes:
        df = df.withColumn(f"d{a}", F.col(f"dst.{a}") - F.col(f"src.{a}"))
    df = df.withColumn("ray", F.sqrt(sum((F.pow(F.col(f"dst.{a}") - F.col(f"src.{a}"), F.lit(2)) for a in "xyz"), F.lit(0.0))))
    lo, hi = [F.lit(0.0)], [F.lit(1.0)]
    for k, a in enumerate(axes):
        low, high = (box[2 * k], box[2 * k + 1]) if box else (-n[a] / 2, n[a] / 2)
        still = F.abs(F.col(f"d{a}")) < 1e-12
        t1, t2 = (low - F.col(f"src.{a}")) / F.col(f"d{a}"), (high - F.col(f"src.{a}")) / F.col(f"d{a}")
        outside = (F.col(f"src.{a}") < low) | (F.col(f"src.{a}") > high)
        lo.append(F.when(still, F.when(outside, 2.0).otherwise(0.0)).otherwise(F.least(t1, t2)))
        hi.append(F.when(still, F.when(outside, -1.0).otherwise(1.0)).otherwise(F.greatest(t1, t2)))
    df = df.withColumns({"t0": F.greatest(*lo), "t1": F.least(*hi)}).where("t0 < t1")

    def crossings(a: str) -> Column:
        """Where the ray meets the axis's planes, between its entry and its exit."""
        every = F.transform(F.sequence(F.lit(0), F.lit(n[a])), lambda i: F.when(F.abs(F.col(f"d{a}")) >= 1e-12, (i - n[a] / 2 - F.col(f"src.{a}")) / F.col(f"d{a}")))
        return F.filter(every, lambda t: (t > F.col("t0")) & (t < F.col("t1")))

    df = df.withColumn("ts", F.array_sort(F.concat(F.array("t0", "t1"), *[crossings(a) for a in axes])))
    df = df.select("rb", "row_id", "view", "sub", "src", "ray", *[f"d{a}" for a in axes], F.explode(F.expr("transform(slice(ts, 1, size(ts) - 1), (t, i) -> struct(t AS t, ts[i + 1] AS u))")).alias("part"))
    mid = (F.col("part.t") + F.col("part.u")) / 2
    df = df.withColumn("val", (F.col("part.u") - F.col("part.t")) * F.col("ray")).where(F.col("val") > SHORT)
    at = {a: F.least(F.greatest(F.floor(F.col(f"src.{a}") + mid * F.col(f"d{a}") + n[a] / 2), F.lit(0)), F.lit(n[a] - 1)) for a in axes}
    col = at["x"] + n["x"] * at["y"] + (n["x"] * n["y"] * at["z"] if "z" in axes else F.lit(0))
    return df.select("rb", "row_id", "view", "sub", col.cast("bigint").alias("col_id"), "val")


def _views(spark: SparkSession, views: int, read: DataFrame | None) -> DataFrame:
    return spark.range(views).select(F.col("id").cast("int").alias("view")) if read is None else read.select("view").distinct()


def shadow_2d(spark: SparkSession, views: int, dets: int, radius: float, pitch: float, subs: int, shape: tuple[int, int], parts: tuple[int, int], phase: float = 1e-3, read: DataFrame | None = None) -> DataFrame:
    """cb, rb, view, sub, p_s: overlap of each block's shadow on the detector line with each sub-area, in closed form. ``read``: rays; only views with one are wanted."""
    blocks = spark.createDataFrame([b[:5] for b in cuboids(shape, parts)], "cb int, x0 double, x1 double, y0 double, y1 double")
    df = blocks.crossJoin(_views(spark, views, read)).crossJoin(spark.range(subs).select(F.col("id").cast("int").alias("sub")))
    phi = F.col("view") * (2 * math.pi / views) + phase

    def corner(x: str, y: str) -> Column:
        along = -F.col(x) * F.sin(phi) + F.col(y) * F.cos(phi)
        depth = F.col(x) * F.cos(phi) + F.col(y) * F.sin(phi)
        return along * (2 * radius) / (radius - depth)

    us = [corner(x, y) for x in ("x0", "x1") for y in ("y0", "y1")]
    df = df.withColumns({"lo": F.least(*us), "hi": F.greatest(*us)})
    first = F.ceil(F.col("sub") * dets / subs)
    last = F.ceil((F.col("sub") + 1) * dets / subs)
    a, b = (first - dets / 2) * pitch, (last - dets / 2) * pitch
    p_s = F.greatest(F.lit(0.0), F.least("hi", b) - F.greatest("lo", a))
    return df.select("cb", (F.col("view") * subs + F.col("sub")).cast("int").alias("rb"), "view", "sub", p_s.alias("p_s"))


def _hull(points: list[tuple[float, float]]) -> list[tuple[float, float]]:
    points = sorted(set(points))

    def half(ps):
        out: list = []
        for p in ps:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (p[1] - out[-2][1]) <= (out[-1][1] - out[-2][1]) * (p[0] - out[-2][0]):
                out.pop()
            out.append(p)
        return out[:-1]

    return half(points) + half(points[::-1]) if len(points) > 2 else points


def _clip(poly: list, axis: int, at: float, keep_above: bool) -> list:
    out = []
    for p, q in zip(poly, poly[1:] + poly[:1], strict=True):
        a, b = p[axis] - at, q[axis] - at
        if not keep_above:
            a, b = -a, -b
        if a >= 0:
            out.append(p)
        if a * b < 0:
            t = a / (a - b)
            out.append((p[0] + t * (q[0] - p[0]), p[1] + t * (q[1] - p[1])))
    return out


def _area(poly: list) -> float:
    return abs(sum(p[0] * q[1] - q[0] * p[1] for p, q in zip(poly, poly[1:] + poly[:1], strict=True))) / 2 if len(poly) > 2 else 0.0


def shadow_3d(spark: SparkSession, views: int, side: int, pitch: float, radius: float, distance: float, seed: int, parts_det: int, shape: tuple[int, int, int], parts: tuple[int, int, int], read: DataFrame | None = None) -> DataFrame:
    """cb, rb, view, sub, p_s: area of each block's projected corners' hull inside each sub-area of the detector."""
    frames = {f[0]: f[1:] for f in cone_frames(views, seed)}
    blocks = {b[0]: b[1:] for b in cuboids(shape, parts)}

    @F.pandas_udf("double")
    def area(cb: pd.Series, view: pd.Series, sub: pd.Series) -> pd.Series:
        out = []
        for c, v, s in zip(cb, view, sub, strict=True):
            n, a, b = frames[v][:3], frames[v][3:6], frames[v][6:]
            x0, x1, y0, y1, z0, z1 = blocks[c]
            points = []
            for p in ((x, y, z) for x in (x0, x1) for y in (y0, y1) for z in (z0, z1)):
                dot = lambda w, p=p: sum(i * j for i, j in zip(p, w, strict=True))
                scale = distance / (radius - dot(n))
                points.append((dot(a) * scale, dot(b) * scale))
            poly = _hull(points)
            i, j = divmod(int(s), parts_det)
            edge = lambda k: (-(-k * side // parts_det) - side / 2) * pitch
            for axis, k in ((0, i), (1, j)):
                poly = _clip(_clip(poly, axis, edge(k), True), axis, edge(k + 1), False) if poly else poly
            out.append(_area(poly))
        return pd.Series(out)

    df = spark.range(len(blocks)).select(F.col("id").cast("int").alias("cb")).crossJoin(_views(spark, views, read)).crossJoin(
        spark.range(parts_det * parts_det).select(F.col("id").cast("int").alias("sub"))
    )
    return df.select("cb", (F.col("view") * (parts_det * parts_det) + F.col("sub")).cast("int").alias("rb"), "view", "sub", area("cb", "view", "sub").alias("p_s"))


#: our own nested ellipses: centre x, y, half axes, angle, added density (fractions of the half width)
ELLIPSES = ((0.0, 0.0, 0.9, 0.8, 0.0, 1.0), (0.0, 0.0, 0.8, 0.7, 0.0, -0.6), (0.3, 0.1, 0.2, 0.35, 0.4, 0.5), (-0.3, 0.0, 0.25, 0.4, -0.3, 0.3), (0.0, -0.45, 0.15, 0.1, 0.0, 0.8))


def phantom(grid: DataFrame, shape: tuple[int, ...]) -> DataFrame:
    """``grid`` with x_true: nested ellipses (ellipsoids, with the third half axis the mean of the two) at cell centres."""
    mid = lambda a, k: (F.col(a) + 0.5) / (shape[k] / 2) - 1.0
    value = F.lit(0.0)
    for cx, cy, ra, rb, turn, rho in ELLIPSES:
        x, y = mid("ix", 0) - cx, mid("iy", 1) - cy
        u, v = x * math.cos(turn) + y * math.sin(turn), y * math.cos(turn) - x * math.sin(turn)
        r = F.pow(u / ra, F.lit(2)) + F.pow(v / rb, F.lit(2))
        if len(shape) > 2:
            r = r + F.pow(mid("iz", 2) / ((ra + rb) / 2), F.lit(2))
        value = value + F.when(r <= 1.0, rho).otherwise(0.0)
    return grid.withColumn("x_true", value)
