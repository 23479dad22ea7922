"""Which blocks take part in an epoch. A draw is a function of seed, epoch and block, so a retried task draws the same."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksolve.functions.hashing import uniform, uniform_of
from blocksolve.operators.density import all_pairs, blended
from blocksolve.schema import SolveSpec


def draw_col_blocks(blocks: list[int], spec: SolveSpec, epoch: int) -> list[int]:
    """ceil(col_fraction * n) column blocks without replacement, in their own order."""
    k = math.ceil(spec.col_fraction * len(blocks))
    return sorted(sorted(blocks, key=lambda cb: uniform_of(spec.seed, epoch, "col", cb))[:k])


def weights(density: DataFrame, rows: DataFrame, spec: SolveSpec, epoch: int) -> DataFrame:
    """``density`` with w, the weight of the epoch's sampler."""
    d = all_pairs(density, rows) if spec.keep_empty else density.where("p_s > 0")
    sampler = spec.sampler
    if sampler == "coin":
        sampler = "density" if uniform_of(spec.seed, epoch, "coin") < spec.coin_p else "uniform"
    if sampler == "uniform":
        return d.withColumn("w", F.lit(1.0))
    if sampler == "blend":
        return blended(d, spec.theta(epoch))
    if sampler == "floor":
        return d.withColumn("w", F.greatest("p", F.lit(float(spec.floor))))
    return d.withColumn("w", F.col("p"))


def taken(spec: SolveSpec, m: int) -> int:
    """How many of m row blocks an epoch draws for a column block."""
    take = math.ceil(spec.row_fraction * m - 1e-9)
    if spec.last_group == "full":
        take = min(m, math.ceil(take / spec.group_size) * spec.group_size)
    return take


def draw_row_blocks(density: DataFrame, rows: DataFrame, m: int, spec: SolveSpec, epoch: int, cols: list[int] | None = None) -> DataFrame:
    """epoch, cb, rb, view, pick_rank, grp, p_s, p_t: per column block, ceil(row_fraction * m) row blocks without replacement.

    The keys -ln(u)/w of a weighted draw (Efraimidis and Spirakis 2006): the smallest win, which is the
    same law as drawing one at a time with renewed shares. Groups are runs of ``group_size`` picks.
    """
    take = taken(spec, m)
    d = weights(density, rows, spec, epoch)
    if cols is not None:
        d = d.where(F.col("cb").isin(cols))
    key = F.when(F.col("w") > 0, -F.log(uniform(spec.seed, epoch, F.col("cb"), F.col("rb"))) / F.col("w")).otherwise(F.lit(float("inf")))
    rank = F.row_number().over(Window.partitionBy("cb").orderBy("key", "rb"))
    picked = d.withColumn("key", key).withColumn("pick_rank", rank).where(F.col("pick_rank") <= take)
    return picked.select(F.lit(epoch).cast("int").alias("epoch"), "cb", "rb", "view", F.col("pick_rank").cast("int").alias("pick_rank"), F.floor((F.col("pick_rank") - 1) / spec.group_size).cast("int").alias("grp"), "p_s", "p_t")


def relaxation(picks: DataFrame, spec: SolveSpec, damping: float = 1.0, base: float | None = None) -> DataFrame:
    """cb, grp, beta: the base, or the base times the group's share of the column block's area (unblended); adaptive: the
    latter, with a base that follows the gap."""
    b = spec.step_base if base is None else base
    area = F.sum("p_s") / F.max("p_t")
    beta = F.lit(b * damping) if spec.step_policy == "const" else F.lit(b * damping) * area
    return picks.groupBy("cb", "grp").agg(beta.alias("beta"))


def visits(picks: DataFrame) -> DataFrame:
    return picks.groupBy("cb").agg(F.countDistinct("grp").alias("visits"))
