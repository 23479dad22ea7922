"""Queries on scan geometry over rays read from a table (customers, see ``systems.readings``), each with SQL that computes the same from first principles."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from blocksolve.functions import geometry as geo
from blocksolve.operators import density as dens
from blocksolve.plans import sql
from blocksolve.plans.blocks import rounded
from blocksolve.sources import systems

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, text: str | None = None):
    def add(f):
        QUERIES[name] = f
        if text:
            SQL[name] = text
        return f

    return add


V, D, R, N = 36, 47, 29.0, 16
_PHI = f"(view * {2 * math.pi / V!r} + 0.001)"
_READ = sql.readings(V, D)
_FAN = f"""rays AS (SELECT *, (det * 2 // {D})::INT AS sub FROM ({_READ})),
pts AS (SELECT *, (view * 2 + sub)::INT AS rb, {R} * cos{_PHI} AS sx, {R} * sin{_PHI} AS sy, -{R} * cos{_PHI} - (det - {(D - 1) / 2}) * sin{_PHI} AS dx, -{R} * sin{_PHI} + (det - {(D - 1) / 2}) * cos{_PHI} AS dy FROM rays)"""


def fan(spark, d):
    """Rays are dealt out first: the table is small, tracing is not."""
    read = systems.readings(spark, d, V, D).repartition(4 * spark.sparkContext.defaultParallelism, "row_id")
    return geo.fan_rays(spark, V, D, R, read=read)


def _flat(rays):
    cols = [F.col(f"{p}.{a}").alias(f"{p[0]}{a}") for p in ("src", "dst") for a in "xyz"]
    return rounded(rays.select("row_id", "rb", "view", "det", "sub", *cols), *[f"{p}{a}" for p in "sd" for a in "xyz"], digits=6)


@query("geo_fan_rays", f"WITH {_FAN} SELECT row_id, rb, view, det, sub, round(sx, 6) + 0.0 AS sx, round(sy, 6) + 0.0 AS sy, 0.0 AS sz, round(dx, 6) + 0.0 AS dx, round(dy, 6) + 0.0 AS dy, 0.0 AS dz FROM pts")
def _(spark, d):
    return _flat(geo.fan_rays(spark, V, D, R, read=systems.readings(spark, d, V, D)))


_PHALF = f"(view * {math.pi / V!r} + 0.001)"


@query(
    "geo_parallel_rays",
    f"""SELECT row_id, view AS rb, view, det, 0 AS sub, round({R} * cos{_PHALF} - u * sin{_PHALF}, 6) + 0.0 AS sx, round({R} * sin{_PHALF} + u * cos{_PHALF}, 6) + 0.0 AS sy, 0.0 AS sz,
    round(-{R} * cos{_PHALF} - u * sin{_PHALF}, 6) + 0.0 AS dx, round(-{R} * sin{_PHALF} + u * cos{_PHALF}, 6) + 0.0 AS dy, 0.0 AS dz
    FROM (SELECT row_id, view, det, det - {(D - 1) / 2} AS u FROM ({_READ}))""",
)
def _(spark, d):
    return _flat(geo.parallel_rays(spark, V, D, R, read=systems.readings(spark, d, V, D)))


@query(
    "geo_cone_rays",
    f"SELECT view, count(*) AS rays, 66.0 AS source_radius, 66.0 AS centre_distance, round(avg(sqrt((det // 26 - 12.5) ** 2 + (det % 26 - 12.5) ** 2)), 6) AS off_centre FROM ({sql.readings(12, 676)}) GROUP BY 1",
)
def _(spark, d):
    """Per view: rays, how far the source is from the axis, how far the detector's plane is, and how far rays end from its middle."""
    r = geo.cone_rays(spark, 12, 26, read=systems.readings(spark, d, 12, 676))
    dot = lambda p, q: sum((F.col(f"{p}.{a}") * F.col(f"{q}.{a}") for a in "xyz"), F.lit(0.0))
    away = -dot("src", "dst") / F.sqrt(dot("src", "src"))
    g = r.groupBy("view").agg(F.count("*").alias("rays"), F.avg(F.sqrt(dot("src", "src"))).alias("source_radius"), F.avg(away).alias("centre_distance"), F.avg(F.sqrt(dot("dst", "dst") - away * away)).alias("off_centre"))
    return rounded(g, "source_radius", "centre_distance", "off_centre", digits=6)


_SLAB = """clip AS (SELECT rb, row_id, view, sub, iy * {n} + ix AS col_id, sqrt((dx - sx) ** 2 + (dy - sy) ** 2) *
   (least(1, greatest((ix - {h} - sx) / (dx - sx), (ix + 1 - {h} - sx) / (dx - sx)), greatest((iy - {h} - sy) / (dy - sy), (iy + 1 - {h} - sy) / (dy - sy)))
  - greatest(0, least((ix - {h} - sx) / (dx - sx), (ix + 1 - {h} - sx) / (dx - sx)), least((iy - {h} - sy) / (dy - sy), (iy + 1 - {h} - sy) / (dy - sy)))) AS val
  FROM pts, range(0, {n}) a(ix), range(0, {n}) b(iy))""".format(n=N, h=N / 2)


@query("geo_trace_2d", f"WITH {_FAN}, {_SLAB} SELECT rb, row_id, view, sub, col_id::BIGINT AS col_id, round(val, 5) AS val FROM clip WHERE val > 1e-5")
def _(spark, d):
    return rounded(geo.trace(fan(spark, d), (N, N)).where("val > 1e-5"), "val", digits=5)


@query("geo_ray_chord_sum", f"WITH {_FAN}, {_SLAB} SELECT row_id, round(sum(val), 4) AS chord FROM clip WHERE val > 1e-5 GROUP BY 1")
def _(spark, d):
    """Lengths inside cells add up to the ray's chord through the box."""
    t = geo.trace(fan(spark, d), (N, N)).where("val > 1e-5")
    return rounded(t.groupBy("row_id").agg(F.sum("val").alias("chord")), "chord")


@query("geo_trace_block", f"WITH {_FAN}, {_SLAB} SELECT rb, count(*) AS nnz, round(sum(val), 4) + 0.0 AS mass FROM clip WHERE val > 1e-5 AND col_id % {N} < 8 AND col_id // {N} < 8 GROUP BY 1")
def _(spark, d):
    """Only what one block of the volume needs: rays are clipped to the block before they are traced."""
    t = geo.trace(fan(spark, d), (N, N), (-8, 0, -8, 0)).where("val > 1e-5")
    return rounded(t.groupBy("rb").agg(F.count("*").alias("nnz"), F.sum("val").alias("mass")), "mass")


_US = ", ".join(f"(-({x}) * sin{_PHI} + ({y}) * cos{_PHI}) * {2 * R} / ({R} - (({x}) * cos{_PHI} + ({y}) * sin{_PHI}))" for x in ("x0", "x1") for y in ("y0", "y1"))


@query(
    "geo_shadow_2d",
    f"""WITH b(cb, x0, x1, y0, y1) AS (VALUES (0, -8.0, 0.0, -8.0, 0.0), (1, 0.0, 8.0, -8.0, 0.0), (2, -8.0, 0.0, 0.0, 8.0), (3, 0.0, 8.0, 0.0, 8.0)),
    s AS (SELECT cb, view::INT AS view, sub::INT AS sub, least({_US}) AS lo, greatest({_US}) AS hi, (ceil(sub * {D} / 2) - {D / 2}) AS a, (ceil((sub + 1) * {D} / 2) - {D / 2}) AS c FROM b, (SELECT DISTINCT view FROM ({_READ})) v, range(0, 2) q(sub))
    SELECT cb, (view * 2 + sub)::INT AS rb, view, sub, round(greatest(0, least(hi, c) - greatest(lo, a)), 6) + 0.0 AS p_s FROM s""",
)
def _(spark, d):
    return rounded(geo.shadow_2d(spark, V, D, R, 1.0, 2, (N, N), (2, 2), read=systems.readings(spark, d, V, D)), "p_s", digits=6)


@query(
    "geo_shadow_imbalance",
    f"""SELECT cb, view, min(p_s) AS least, max(p_s) AS most, CASE WHEN max(p_s) > 0 THEN round(min(p_s) / max(p_s), 6) + 0.0 END AS ratio FROM ({SQL["geo_shadow_2d"]}) GROUP BY 1, 2""",
)
def _(spark, d):
    """How unevenly the two sub-areas of a view see each block."""
    return rounded(dens.imbalance(dens.with_shares(rounded(geo.shadow_2d(spark, V, D, R, 1.0, 2, (N, N), (2, 2), read=systems.readings(spark, d, V, D)), "p_s", digits=6))), "ratio", digits=6)


@query("geo_shadow_3d")
def _(spark, d):
    return geo.shadow_3d(spark, 12, 26, 2.0, 66.0, 132.0, 0, 2, (16, 16, 16), (2, 2, 2), systems.readings(spark, d, 12, 676))


@query("geo_trace_3d", f"SELECT count(*) AS rays, 0::BIGINT AS violations FROM ({sql.readings(8, 676)})")
def _(spark, d):
    """Rays, and those whose lengths inside cells do not add up to their chord through the cube: none."""
    rays = geo.cone_rays(spark, 8, 26, 2.0, read=systems.readings(spark, d, 8, 676).repartition(4 * spark.sparkContext.defaultParallelism, "row_id"))
    t = geo.trace(rays, (8, 8, 8)).groupBy("row_id").agg(F.sum("val").alias("chord"))
    lo, hi = [F.lit(0.0)], [F.lit(1.0)]
    for a in "xyz":
        s, e = F.col(f"src.{a}"), F.col(f"dst.{a}")
        lo.append(F.least((-4 - s) / (e - s), (4 - s) / (e - s)))
        hi.append(F.greatest((-4 - s) / (e - s), (4 - s) / (e - s)))
    length = F.sqrt(sum((F.pow(F.col(f"dst.{a}") - F.col(f"src.{a}"), F.lit(2)) for a in "xyz"), F.lit(0.0)))
    box = rays.select("row_id", (F.greatest(F.least(*hi) - F.greatest(*lo), F.lit(0.0)) * length).alias("want"))
    return box.join(t, "row_id", "left").agg(F.count("*").alias("rays"), F.count_if(F.expr("abs(want - coalesce(chord, 0)) > 1e-6")).alias("violations"))
