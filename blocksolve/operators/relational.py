"""Joins and windows that users of the solver need around it: range, interval and as-of joins, packed rows, sparse maps."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, spans: DataFrame, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points in spans (lo <= at <= hi). Spans are laid over buckets of ``width``, so the join is an equi-join on buckets with a
    residual condition, not a nested loop. A point lies in one bucket, so no pair appears twice."""
    p = points.withColumn("_bucket", F.floor(F.col(at) / width))
    s = spans.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return p.join(s, "_bucket").where((F.col(at) >= F.col(lo)) & (F.col(at) <= F.col(hi))).drop("_bucket")


def as_of(left: DataFrame, right: DataFrame, keys: list[str], at: str, value: str) -> DataFrame:
    """Each left row with the last right value at or before it, as one union and one window: no join, one shuffle by key."""
    other = [c for c in left.columns if c not in (*keys, at)]
    both = left.select(*keys, at, F.lit(1).alias("_side"), *other, F.lit(None).cast(right.schema[value].dataType).alias("_value")).unionByName(
        right.select(*keys, at, F.lit(0).alias("_side"), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in other], F.col(value).alias("_value"))
    )
    last = F.last("_value", ignorenulls=True).over(Window.partitionBy(*keys).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn(value if value not in other else f"{value}_then", last).where("_side = 1").drop("_side", "_value")


def nearest_second(ts: str) -> Column:
    """Seconds since 1970, rounded to the nearest whole one (halves to the even one)."""
    return F.rint(F.unix_micros(F.col(ts).cast("timestamp")) / 1e6).cast("bigint")


def interval_join(a: DataFrame, b: DataFrame, key: str, ta: str, tb: str, seconds: int) -> DataFrame:
    """Pairs of one key with ta < tb whose nearest whole seconds are at most ``seconds`` apart, bucketed by time."""
    x = a.withColumn("_sa", nearest_second(ta)).withColumn("_bucket", F.floor(F.col("_sa") / seconds))
    y = b.withColumn("_sb", nearest_second(tb)).withColumn("_b", F.floor(F.col("_sb") / seconds)).withColumn("_bucket", F.explode(F.array("_b", F.col("_b") - 1))).drop("_b")
    near = (F.col(tb) > F.col(ta)) & (F.col("_sb") - F.col("_sa") <= seconds)
    return x.join(y, [key, "_bucket"]).where(near).drop("_bucket", "_sa", "_sb")


def sparse_rows(entries: DataFrame) -> DataFrame:
    """row_id, row: each row as a map from column to value, for interchange only."""
    return entries.groupBy("row_id").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("col_id", "val")))).alias("row"))


def dot(a: str | Column, b: str | Column) -> Column:
    """Inner product of two arrays."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def top_moved(before: DataFrame, after: DataFrame, k: int) -> DataFrame:
    """col_id, moved: the k unknowns that changed most."""
    moved = before.select("col_id", F.col("x").alias("a")).join(after.select("col_id", "x"), "col_id")
    return moved.select("col_id", F.abs(F.col("x") - F.col("a")).alias("moved")).orderBy(F.desc("moved"), "col_id").limit(k)
