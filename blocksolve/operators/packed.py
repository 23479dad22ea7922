"""Packed blocks: one row per (cb, rb) with its entries in compressed rows, stepped by an Arrow kernel.

A task holds one block and the slices r_I and x_J that it touches: O(|I| + |J|) numbers besides the block. With
groups of one block, g, A g, the step and the projection come from one pass over the entries; with larger groups a first
pass returns partial gradients, Spark adds them over the group, and a second pass returns A x and A g.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pack(entries: DataFrame) -> DataFrame:
    """cb, rb, rows, cols, at (place in rows), idx (place in cols), val."""
    e = entries.groupBy("cb", "rb").agg(
        F.array_sort(F.collect_set("row_id")).alias("rows"), F.array_sort(F.collect_set("col_id")).alias("cols"), F.sort_array(F.collect_list(F.struct("row_id", "col_id", "val"))).alias("e")
    )

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[list] = [[], [], []]
            for i in range(b.num_rows):
                rows, cols = b.column(2)[i].values.to_numpy(), b.column(3)[i].values.to_numpy()
                one = b.column(4)[i].values
                row, col, val = (one.field(k).to_numpy(zero_copy_only=False) for k in range(3))
                out[0].append(np.searchsorted(rows, row).astype(np.int32))
                out[1].append(np.searchsorted(cols, col).astype(np.int32))
                out[2].append(val)
            yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(out[0], pa.list_(pa.int32())), pa.array(out[1], pa.list_(pa.int32())), pa.array(out[2], pa.list_(pa.float64()))], ["cb", "rb", "rows", "cols", "at", "idx", "val"])

    return e.mapInArrow(made, "cb int, rb int, rows array<bigint>, cols array<bigint>, at array<int>, idx array<int>, val array<double>")


def unpack(blocks: DataFrame) -> DataFrame:
    """Entries again, whichever form they have."""
    if "at" not in blocks.columns:
        return blocks
    each = blocks.select("cb", "rb", "rows", "cols", F.explode(F.arrays_zip("at", "idx", "val")).alias("e"))
    return each.select("cb", "rb", F.get("rows", F.col("e.at")).alias("row_id"), F.get("cols", F.col("e.idx")).alias("col_id"), F.col("e.val").alias("val"))


def slices(v: DataFrame, key: str, index: str, value: str) -> DataFrame:
    """key, ids, values: a block's slice of a vector in the order of its index."""
    return v.groupBy(key).agg(F.sort_array(F.collect_list(F.struct(index, value))).alias("s")).select(key, F.col(f"s.{index}").alias(f"{key}_ids"), F.col(f"s.{value}").alias(f"{key}_values"))


def _blocks(b: pa.RecordBatch, i: int, first: int) -> tuple:
    get = lambda c: b.column(c)[i].values.to_numpy(zero_copy_only=False)
    rows, cols, at, idx, val = (get(first + k) for k in range(5))
    r_ids, r, x_ids, x = (get(first + 5 + k) for k in range(4))
    return rows, cols, at, idx, val, r[np.searchsorted(r_ids, rows)], x[np.searchsorted(x_ids, cols)]


def step_single(joined: DataFrame) -> DataFrame:
    """Groups of one block. Gives per block the moved columns (mu * g) and the rows' projections (z)."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            move, z = [], []
            beta = b.column(2).to_numpy()
            for i in range(b.num_rows):
                rows, cols, at, idx, val, r, x = _blocks(b, i, 3)
                g = np.bincount(idx, val * r[at], len(cols))
                ag = np.bincount(at, val * g[idx], len(rows))
                den = ag @ ag
                mu = beta[i] * (g @ g) / den if den > 0 else 0.0
                move.append(mu * g)
                z.append(np.bincount(at, val * x[idx], len(rows)) + mu * ag)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(4), pa.array(move, pa.list_(pa.float64())), b.column(3), pa.array(z, pa.list_(pa.float64()))], ["cb", "rb", "cols", "move", "rows", "z"])

    return joined.select("cb", "rb", "beta", "rows", "cols", "at", "idx", "val", "rb_ids", "rb_values", "cb_ids", "cb_values").mapInArrow(
        made, "cb int, rb int, cols array<bigint>, move array<double>, rows array<bigint>, z array<double>"
    )


def step_grouped(joined: DataFrame, beta: DataFrame, keep=lambda df, name: df) -> tuple[DataFrame, DataFrame]:
    """Groups of several blocks: (cb, col_id, move) summed over groups, and (cb, rb, row_id, z)."""
    fields = ["rows", "cols", "at", "idx", "val", "rb_ids", "rb_values", "cb_ids", "cb_values"]

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            g = []
            for i in range(b.num_rows):
                rows, cols, at, idx, val, r, x = _blocks(b, i, 2)
                g.append(np.bincount(idx, val * r[at], len(cols)))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(3), pa.array(g, pa.list_(pa.float64()))], ["cb", "grp", "cols", "g"])

    part = joined.select("cb", "grp", *fields).mapInArrow(first, "cb int, grp int, cols array<bigint>, g array<double>")
    g = part.select("cb", "grp", F.explode(F.arrays_zip("cols", "g")).alias("e")).groupBy("cb", "grp", F.col("e.cols").alias("col_id")).agg(F.sum("e.g").alias("g"))
    g = keep(g, "gradients")
    g_slices = g.groupBy("cb", "grp").agg(F.sort_array(F.collect_list(F.struct("col_id", "g"))).alias("s"), F.sum(F.col("g") * F.col("g")).alias("num")).select("cb", "grp", F.col("s.col_id").alias("g_ids"), F.col("s.g").alias("g_values"), "num")

    def second(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ax, ag, den = [], [], []
            for i in range(b.num_rows):
                rows, cols, at, idx, val, r, x = _blocks(b, i, 3)
                ids, values = b.column(12)[i].values.to_numpy(), b.column(13)[i].values.to_numpy()
                gg = values[np.searchsorted(ids, cols)]
                ax.append(np.bincount(at, val * x[idx], len(rows)))
                ag.append(np.bincount(at, val * gg[idx], len(rows)))
                den.append(float(ag[-1] @ ag[-1]))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), b.column(3), pa.array(ax, pa.list_(pa.float64())), pa.array(ag, pa.list_(pa.float64())), pa.array(den)], ["cb", "grp", "rb", "rows", "ax", "ag", "den"])

    f = joined.join(g_slices, ["cb", "grp"]).select("cb", "grp", "rb", *fields, "g_ids", "g_values").mapInArrow(second, "cb int, grp int, rb int, rows array<bigint>, ax array<double>, ag array<double>, den double")
    f = keep(f, "projections")
    den = f.groupBy("cb", "grp").agg(F.sum("den").alias("den"))
    mu = beta.join(g_slices.select("cb", "grp", "num"), ["cb", "grp"]).join(den, ["cb", "grp"]).select("cb", "grp", F.when(F.col("den") > 0, F.col("beta") * F.col("num") / F.col("den")).otherwise(0.0).alias("mu"))
    move = g.join(mu, ["cb", "grp"]).groupBy("cb", "col_id").agg(F.sum(F.col("mu") * F.col("g")).alias("move"))
    z = f.join(mu, ["cb", "grp"]).select("cb", "rb", F.explode(F.arrays_zip("rows", "ax", "ag")).alias("e"), "mu").select("cb", "rb", F.col("e.rows").alias("row_id"), (F.col("e.ax") + F.col("mu") * F.col("e.ag")).alias("z"))
    return move, z
