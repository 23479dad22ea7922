"""How much of each column block a row block sees."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def with_shares(p_s: DataFrame) -> DataFrame:
    """Adds p_t (the column block's total) and p = p_s / p_t, which sums to 1 for each column block."""
    total = F.sum("p_s").over(Window.partitionBy("cb"))
    return p_s.withColumn("p_t", total).withColumn("p", F.when(F.col("p_t") > 0, F.col("p_s") / F.col("p_t")).otherwise(0.0))


def entry_density(entries: DataFrame, rows: DataFrame, weight: str = "nnz") -> DataFrame:
    """cb, rb, view, p_s, p_t, p from stored entries: their number, squared mass or sum."""
    value = {"nnz": F.count("*").cast("double"), "mass": F.sum(F.col("val") * F.col("val")), "sum": F.sum("val")}[weight]
    views = rows.groupBy("rb").agg(F.min("view").alias("view"))
    p_s = entries.groupBy("cb", "rb").agg(value.alias("p_s")).join(views, "rb").select("cb", "rb", "view", "p_s")
    return with_shares(p_s)


def blended(density: DataFrame, theta: float) -> DataFrame:
    """Each area moved toward the largest of its view (and column block) by theta; adds w, the new weight."""
    top = F.max("p_s").over(Window.partitionBy("cb", "view"))
    return density.withColumn("w", (F.col("p_s") + theta * (top - F.col("p_s"))) / F.col("p_t"))


def imbalance(density: DataFrame) -> DataFrame:
    """cb, view, least, most, ratio: how unevenly a view's sub-areas see a column block."""
    return density.groupBy("cb", "view").agg(F.min("p_s").alias("least"), F.max("p_s").alias("most")).withColumn("ratio", F.when(F.col("most") > 0, F.col("least") / F.col("most")))


def all_pairs(density: DataFrame, rows: DataFrame) -> DataFrame:
    """Adds blocks without entries (p_s = 0). The grid of block ids is small next to the data."""
    views = rows.groupBy("rb").agg(F.min("view").alias("view"))
    grid = density.select("cb", "p_t").distinct().crossJoin(views)
    return grid.join(density.select("cb", "rb", "p_s", "p"), ["cb", "rb"], "left").select("cb", "rb", "view", F.coalesce("p_s", F.lit(0.0)).alias("p_s"), "p_t", F.coalesce("p", F.lit(0.0)).alias("p"))
