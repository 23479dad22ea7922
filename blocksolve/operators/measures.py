"""Accuracy and cost measures. All give DataFrames; decibels of an error that is exactly 0 are null."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksolve.operators.step import true_residual


def _db(num, den):
    return F.when(den > 0, 10 * F.log10(num / den))


def snr_db(x_true: DataFrame, x: DataFrame) -> DataFrame:
    """snr_db: squared norm of the truth over that of the error. A column missing on either side counts as 0."""
    t, e = x_true.select("col_id", F.col("x").alias("t")), x.select("col_id", F.col("x").alias("e"))
    both = t.join(e, "col_id", "full").select(F.coalesce("t", F.lit(0.0)).alias("t"), F.coalesce("e", F.lit(0.0)).alias("e"))
    return both.agg(F.sum(F.col("t") * F.col("t")).alias("a"), F.sum(F.pow(F.col("t") - F.col("e"), F.lit(2))).alias("b")).select(_db(F.col("a"), F.col("b")).alias("snr_db"))


def snr_by_region(x_true: DataFrame, x: DataFrame, regions: DataFrame) -> DataFrame:
    """region, snr_db. ``regions``: col_id, region."""
    both = x_true.select("col_id", F.col("x").alias("t")).join(x.select("col_id", F.col("x").alias("e")), "col_id", "left").join(regions, "col_id")
    error = F.pow(F.col("t") - F.coalesce("e", F.lit(0.0)), F.lit(2))
    return both.groupBy("region").agg(F.sum(F.col("t") * F.col("t")).alias("a"), F.sum(error).alias("b")).select("region", _db(F.col("a"), F.col("b")).alias("snr_db"))


def surrogate_gap_db(y: DataFrame, r: DataFrame) -> DataFrame:
    both = y.join(r.select("row_id", "r"), "row_id")
    return both.agg(F.sum(F.col("y") * F.col("y")).alias("a"), F.sum(F.col("r") * F.col("r")).alias("b")).select(_db(F.col("a"), F.col("b")).alias("gap_db"))


def gap_db(entries: DataFrame, x: DataFrame, y: DataFrame) -> DataFrame:
    """gap_db: squared norm of the observations over that of the true residual (larger is better)."""
    return surrogate_gap_db(y, true_residual(entries, y, x))


# --- cost -------------------------------------------------------------------------------------


def block_stats(entries: DataFrame) -> DataFrame:
    """cb, rb, nnz, n_rows, n_cols of the stored blocks."""
    return entries.groupBy("cb", "rb").agg(F.count("*").alias("nnz"), F.countDistinct("row_id").alias("n_rows"), F.countDistinct("col_id").alias("n_cols"))


def macs(picks: DataFrame, stats: DataFrame) -> DataFrame:
    """epoch, macs: three passes over a picked block's entries (back, A x, A g)."""
    return picks.join(stats, ["cb", "rb"]).groupBy("epoch").agg((3 * F.sum("nnz")).alias("macs"))


def transfer(picks: DataFrame, stats: DataFrame) -> DataFrame:
    """epoch, numbers: slices of r and x sent to each task, proposal and projection sent back."""
    return picks.join(stats, ["cb", "rb"]).groupBy("epoch").agg((2 * F.sum(F.col("n_rows") + F.col("n_cols"))).alias("numbers"))


def memory(picks: DataFrame, stats: DataFrame) -> DataFrame:
    """epoch, local_numbers: the most numbers that one task holds besides its block."""
    return picks.join(stats, ["cb", "rb"]).groupBy("epoch").agg(F.max(F.col("n_rows") + F.col("n_cols")).alias("local_numbers"))


def effective_epochs(picks: DataFrame, m: int, n: int) -> DataFrame:
    """epoch, eff_epoch: picks so far over all block pairs."""
    per = picks.groupBy("epoch").agg(F.count("*").alias("picks"))
    return per.select("epoch", (F.sum("picks").over(Window.orderBy("epoch")) / float(m * n)).alias("eff_epoch"))


def refresh_counts(picks: DataFrame) -> DataFrame:
    """cb, rb, refreshes: how often a block's projection was renewed."""
    return picks.groupBy("cb", "rb").agg(F.count("*").alias("refreshes"))


# --- histories (run, epoch, eff_epoch, snr_db, gap_db) -----------------------------------------


def mean_history(history: DataFrame) -> DataFrame:
    """epoch, snr_db, gap_db: means over runs."""
    return history.groupBy("epoch").agg(F.avg("snr_db").alias("snr_db"), F.avg("gap_db").alias("gap_db"))


def sampler_gain(a: DataFrame, b: DataFrame) -> DataFrame:
    """epoch, gain_db: mean SNR of the runs of ``a`` minus that of ``b``."""
    left, right = mean_history(a).select("epoch", F.col("snr_db").alias("sa")), mean_history(b).select("epoch", F.col("snr_db").alias("sb"))
    return left.join(right, "epoch").select("epoch", (F.col("sa") - F.col("sb")).alias("gain_db"))


def plateaus(history: DataFrame, eps: float = 0.05, least: int = 2) -> DataFrame:
    """run, first_epoch, last_epoch: stretches of ``least`` steps or more that gain less than ``eps`` dB each, before the run's best is reached."""
    w = Window.partitionBy("run").orderBy("epoch")
    best = F.max("gap_db").over(Window.partitionBy("run"))
    flat = history.withColumn("flat", ((F.col("gap_db") - F.lag("gap_db").over(w)) < eps) & (F.col("gap_db") < best - eps)).where("flat")
    island = flat.withColumn("island", F.col("epoch") - F.row_number().over(w))
    return island.groupBy("run", "island").agg(F.min("epoch").alias("first_epoch"), F.max("epoch").alias("last_epoch"), F.count("*").alias("n")).where(F.col("n") >= least).select("run", "first_epoch", "last_epoch")


def diverged(history: DataFrame) -> DataFrame:
    """run, diverged: the gap ends below where it began, or is no number."""
    ends = history.groupBy("run").agg(F.min_by("gap_db", "epoch").alias("a"), F.max_by("gap_db", "epoch").alias("b"))
    return ends.select("run", (F.isnan("b") | (F.col("b") < F.col("a"))).alias("diverged"))


def epochs_to(history: DataFrame, db: float) -> DataFrame:
    """run, epoch: the first epoch at or above ``db`` (null if none)."""
    return history.groupBy("run").agg(F.min(F.when(F.col("gap_db") >= db, F.col("epoch"))).alias("epoch"))
