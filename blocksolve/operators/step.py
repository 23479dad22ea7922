"""One round of block steps as joins and aggregations.

``active`` is entries joined with picks: (cb, grp, rb, row_id, col_id, val). A group is the union of its row
blocks: its gradient is summed over members before the step is computed, so no task ever needs a whole group.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def activate(entries: DataFrame, picks: DataFrame) -> DataFrame:
    """Entries of the picked blocks. Picks are at most one row a block pair; Spark broadcasts them while they are small."""
    return entries.join(picks.select("cb", "rb", "grp"), ["cb", "rb"])


def back_project(active: DataFrame, r: DataFrame) -> DataFrame:
    """cb, grp, col_id, g: the residual carried back through the active entries."""
    joined = active.join(r.select("row_id", "r"), "row_id")
    return joined.groupBy("cb", "grp", "col_id").agg(F.sum(F.col("val") * F.col("r")).alias("g"))


def with_x(g: DataFrame, x: DataFrame, ridge: float = 0.0) -> DataFrame:
    """cb, grp, col_id, x, g, with the ridge term's part of the direction."""
    out = g.join(x.select("cb", "col_id", "x"), ["cb", "col_id"])
    return out.withColumn("g", F.col("g") - ridge * F.col("x")) if ridge else out


def forward_pair(active: DataFrame, xg: DataFrame) -> DataFrame:
    """cb, grp, rb, row_id, ax, ag: A x and A g of every active row in one pass over the entries."""
    joined = active.join(xg, ["cb", "grp", "col_id"])
    return joined.groupBy("cb", "grp", "rb", "row_id").agg(F.sum(F.col("val") * F.col("x")).alias("ax"), F.sum(F.col("val") * F.col("g")).alias("ag"))


def forward_project(active: DataFrame, x_local: DataFrame) -> DataFrame:
    """cb, rb, row_id, z of local proposals (cb, grp, col_id, x)."""
    joined = active.join(x_local, ["cb", "grp", "col_id"])
    return joined.groupBy("cb", "rb", "row_id").agg(F.sum(F.col("val") * F.col("x")).alias("z"))


def step_length(xg: DataFrame, f: DataFrame, beta: DataFrame, ridge: float = 0.0) -> DataFrame:
    """cb, grp, beta, num, den, mu: exact line search times beta; 0 where the direction is 0."""
    num = xg.groupBy("cb", "grp").agg(F.sum(F.col("g") * F.col("g")).alias("num"))
    den = f.groupBy("cb", "grp").agg(F.sum(F.col("ag") * F.col("ag")).alias("den"))
    both = beta.join(num, ["cb", "grp"], "left").join(den, ["cb", "grp"], "left").select("cb", "grp", "beta", F.coalesce("num", F.lit(0.0)).alias("num"), F.coalesce("den", F.lit(0.0)).alias("den"))
    whole = F.col("den") + ridge * F.col("num")
    return both.withColumn("mu", F.when(whole > 0, F.col("beta") * F.col("num") / whole).otherwise(0.0))


def propose(xg: DataFrame, mu: DataFrame) -> DataFrame:
    """cb, grp, col_id, x: local proposals of the columns with active entries (the others keep their value)."""
    return xg.join(mu.select("cb", "grp", "mu"), ["cb", "grp"]).select("cb", "grp", "col_id", (F.col("x") + F.col("mu") * F.col("g")).alias("x"))


def average(x: DataFrame, xg: DataFrame, mu: DataFrame, visits: DataFrame) -> DataFrame:
    """cb, col_id, x: the mean of all proposals over the visits of a column block.

    A group without a gradient for a column proposes its old value, so the sum of the moves is divided
    by the number of visits and not by how many groups touched the column.
    """
    move = xg.join(mu.select("cb", "grp", "mu"), ["cb", "grp"]).groupBy("cb", "col_id").agg(F.sum(F.col("mu") * F.col("g")).alias("move"))
    out = x.join(move, ["cb", "col_id"], "left").join(visits, "cb", "left")
    return out.select("cb", "col_id", (F.col("x") + F.coalesce(F.col("move") / F.col("visits"), F.lit(0.0))).alias("x"))


def partial_projections(f: DataFrame, mu: DataFrame) -> DataFrame:
    """cb, rb, row_id, z: A times the local proposal."""
    return f.join(mu.select("cb", "grp", "mu"), ["cb", "grp"]).select("cb", "rb", "row_id", (F.col("ax") + F.col("mu") * F.col("ag")).alias("z"))


def residual_step(r: DataFrame, f: DataFrame, mu: DataFrame) -> DataFrame:
    """rb, row_id, r: the residual after one group's step, by update instead of recomputation."""
    moved = f.join(mu.select("cb", "grp", "mu"), ["cb", "grp"]).groupBy("row_id").agg(F.sum(F.col("mu") * F.col("ag")).alias("d"))
    return r.join(moved, "row_id", "left").select("rb", "row_id", (F.col("r") - F.coalesce("d", F.lit(0.0))).alias("r"))


def merge_z(z: DataFrame, fresh: DataFrame, picks: DataFrame) -> DataFrame:
    """Picked blocks take their fresh projections; the others keep what they had."""
    return z.join(picks.select("cb", "rb"), ["cb", "rb"], "left_anti").unionByName(fresh)


def surrogate_residual(y: DataFrame, z: DataFrame) -> DataFrame:
    """rb, row_id, r = y minus all stored partial projections."""
    total = z.groupBy("row_id").agg(F.sum("z").alias("zsum"))
    return y.join(total, "row_id", "left").select("rb", "row_id", (F.col("y") - F.coalesce("zsum", F.lit(0.0))).alias("r"))


def surrogate_residual_touched(r: DataFrame, old: DataFrame, fresh: DataFrame, touched: DataFrame) -> DataFrame:
    """The same from the last residual: only rows of ``touched`` row blocks change, by what their projections changed."""
    delta = fresh.select("row_id", "rb", F.col("z").alias("d")).unionByName(old.select("row_id", "rb", (-F.col("z")).alias("d")))
    delta = delta.join(touched.select("rb").distinct(), "rb", "left_semi").groupBy("row_id").agg(F.sum("d").alias("d"))
    return r.join(delta, "row_id", "left").select("rb", "row_id", (F.col("r") - F.coalesce("d", F.lit(0.0))).alias("r"))


def true_residual(entries: DataFrame, y: DataFrame, x: DataFrame) -> DataFrame:
    """rb, row_id, r = y - A x."""
    ax = entries.join(x.select("col_id", "x"), "col_id").groupBy("row_id").agg(F.sum(F.col("val") * F.col("x")).alias("ax"))
    return y.join(ax, "row_id", "left").select("rb", "row_id", (F.col("y") - F.coalesce("ax", F.lit(0.0))).alias("r"))


def objective(entries: DataFrame, x: DataFrame, y: DataFrame, rows: DataFrame | None = None) -> DataFrame:
    """One row: the squared norm of y - A x, over ``rows`` only if given."""
    r = true_residual(entries, y, x)
    if rows is not None:
        r = r.join(rows.select("row_id"), "row_id", "left_semi")
    return r.agg(F.coalesce(F.sum(F.col("r") * F.col("r")), F.lit(0.0)).alias("objective"))
