"""Row-action and column-action methods, as yardsticks.

A row action corrects all of x from row blocks: x += omega C A_I^T W (y_I - A_I x). A column action corrects one
column block from all of r and updates r. Inner loops run one after the other, or at once with their moves summed or averaged.
Methods that need one equation or one unknown at a time run inside one task.
"""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksolve.operators.step import true_residual
from blocksolve.schema import LinearSystem
from blocksolve.sources.store import commit


def row_weights(entries: DataFrame, weight: str) -> DataFrame:
    """rb, row_id, w. none: 1; row_norm: one over the squared norm; sart, sirt: one over the row's sum; cav, bicav:
    one over the sum of s * a^2 with s the nonzeros of the column in the matrix (cav) or in the row block (bicav)."""
    if weight in ("cav", "bicav"):
        keys = ["col_id"] if weight == "cav" else ["rb", "col_id"]
        s = entries.groupBy(*keys).agg(F.count("*").alias("s"))
        total = entries.join(s, keys).groupBy("rb", "row_id").agg(F.sum(F.col("s") * F.col("val") * F.col("val")).alias("t"))
    else:
        value = {"none": F.lit(1.0), "row_norm": F.sum(F.col("val") * F.col("val")), "sart": F.sum("val"), "sirt": F.sum("val")}[weight]
        total = entries.groupBy("rb", "row_id").agg(F.count("*"), value.alias("t"))
    return total.select("rb", "row_id", F.when(F.col("t") != 0, 1.0 / F.col("t")).otherwise(0.0).alias("w"))


def col_scales(entries: DataFrame, weight: str) -> DataFrame | None:
    """col_id (and rb for sart), c: one over the column's sum, in the matrix (sirt) or in the row block (sart)."""
    keys = {"sirt": ["col_id"], "sart": ["rb", "col_id"]}.get(weight)
    return keys and entries.groupBy(*keys).agg(F.sum("val").alias("t")).select(*keys, F.when(F.col("t") != 0, 1.0 / F.col("t")).otherwise(0.0).alias("c"))


def row_moves(system: LinearSystem, x: DataFrame, weight: str, omega: float, blocks: list[int] | None = None) -> DataFrame:
    """rb, col_id, move of each row block from the same x."""
    e = system.entries if blocks is None else system.entries.where(F.col("rb").isin(blocks))
    y = system.y if blocks is None else system.y.where(F.col("rb").isin(blocks))
    r = true_residual(e, y, x).join(row_weights(system.entries, weight), ["rb", "row_id"]).select("row_id", (F.col("r") * F.col("w")).alias("r"))
    g = e.join(r, "row_id").groupBy("rb", "col_id").agg(F.sum(F.col("val") * F.col("r")).alias("g"))
    c = col_scales(system.entries, weight)
    if c is None:
        return g.select("rb", "col_id", (omega * F.col("g")).alias("move"))
    return g.join(c, [k for k in c.columns if k != "c"]).select("rb", "col_id", (omega * F.col("c") * F.col("g")).alias("move"))


def _moved(x: DataFrame, move: DataFrame) -> DataFrame:
    total = move.groupBy("col_id").agg(F.sum("move").alias("move"))
    return x.join(total, "col_id", "left").select("cb", "col_id", (F.col("x") + F.coalesce("move", F.lit(0.0))).alias("x"))


def row_action(system: LinearSystem, x: DataFrame, blocks: list[int], weight: str = "row_norm", omega: float = 1.0, mode: str = "sequential") -> DataFrame:
    """x after one sweep over the row blocks. In sequence, x is committed between blocks: each block's plan uses it twice and would double with every block."""
    if mode == "sequential":
        for k, rb in enumerate(blocks):
            x = commit(x, "x") if k else x
            x = _moved(x, row_moves(system, x, weight, omega, [rb]))
        return x
    share = 1.0 if mode == "sum" else 1.0 / len(blocks)
    return _moved(x, row_moves(system, x, weight, omega * share))


def col_action(system: LinearSystem, x: DataFrame, blocks: list[int], weight: str = "exact1d", omega: float = 1.0, mode: str = "sequential") -> DataFrame:
    """x after one sweep over the column blocks. exact1d: one over the column's squared norm; steepest: exact line search of the block.
    In sequence, moves and residuals are committed between blocks, as a block's plan uses them several times."""
    scale = system.entries.groupBy("col_id").agg((1.0 / F.sum(F.col("val") * F.col("val"))).alias("c"))

    def move(cbs: list[int], r: DataFrame) -> DataFrame:
        e = system.entries.where(F.col("cb").isin(cbs))
        g = e.join(r.select("row_id", "r"), "row_id").groupBy("cb", "col_id").agg(F.sum(F.col("val") * F.col("r")).alias("g"))
        if weight == "exact1d":
            return g.join(scale, "col_id").select("col_id", (omega * F.col("c") * F.col("g")).alias("move"))
        ag = e.join(g, ["cb", "col_id"]).groupBy("cb", "row_id").agg(F.sum(F.col("val") * F.col("g")).alias("ag")).groupBy("cb").agg(F.sum(F.col("ag") * F.col("ag")).alias("den"))
        mu = g.groupBy("cb").agg(F.sum(F.col("g") * F.col("g")).alias("num")).join(ag, "cb").select("cb", F.when(F.col("den") > 0, F.col("num") / F.col("den")).otherwise(0.0).alias("mu"))
        return g.join(mu, "cb").select("col_id", (omega * F.col("mu") * F.col("g")).alias("move"))

    r = true_residual(system.entries, system.y, x)
    if mode != "sequential":
        share = 1.0 if mode == "sum" else 1.0 / len(blocks)
        return _moved(x, move(blocks, r).withColumn("move", F.col("move") * share))
    for k, cb in enumerate(blocks):
        d = move([cb], r)
        if k == len(blocks) - 1:
            return _moved(x, d)
        d = commit(d, "move")
        x = commit(_moved(x, d), "x")
        ad = system.entries.join(d, "col_id").groupBy("row_id").agg(F.sum(F.col("val") * F.col("move")).alias("d"))
        r = commit(r.join(ad, "row_id", "left").select("rb", "row_id", (F.col("r") - F.coalesce("d", F.lit(0.0))).alias("r")), "r")
    return x


# --- one at a time, inside one task -----------------------------------------------------------------


CHUNK = 1 << 22  # entries that a step over all of them takes at once


def _whole(system: LinearSystem, kernel, most: int | None = None, by: str = "row") -> DataFrame:
    """Runs ``kernel(row, col, val, y, n)`` in one task over the whole system, entries ordered by row or by column; ValueError beyond ``most`` entries, if given.

    The task holds a few numbers a row and a column; entries lie in files of its own, so memory does not grow with them. Spark sorts
    and numbers them; they arrive as runs of consecutive numbers, which are put in order.
    """
    if most is not None and (n := system.entries.count()) > most:
        raise ValueError(f"{n} entries; one task may hold {most}: use row_action or col_action over blocks")
    major, minor = ("row_id", "col_id") if by == "row" else ("col_id", "row_id")
    e = commit(system.entries.select(F.lit(0).alias("kind"), "row_id", "col_id", "val").repartitionByRange(major).sortWithinPartitions(major, minor).withColumn("n", F.monotonically_increasing_id()), "sorted")
    y = system.y.select(F.lit(1).alias("kind"), "row_id", F.lit(0).cast("bigint").alias("col_id"), F.col("y").alias("val"), F.lit(0).cast("bigint").alias("n"))
    c = system.cols.select(F.lit(2).alias("kind"), F.lit(0).cast("bigint").alias("row_id"), "col_id", F.lit(0.0).alias("val"), F.lit(0).cast("bigint").alias("n"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with tempfile.TemporaryDirectory(dir=os.environ.get("SPARK_LOCAL_DIRS", "").split(",")[0] or None) as folder:
            ys, cs, runs, last, total = [], [], [], -2, 0
            with open(f"{folder}/ids", "wb") as ids, open(f"{folder}/came", "wb") as came:
                for batch in batches:
                    kind, row, col, val, n = (batch.column(k).to_numpy() for k in range(5))
                    ys.append((row[kind == 1], val[kind == 1]))
                    cs.append(col[kind == 2])
                    some = kind == 0
                    if not some.any():
                        continue
                    key, n = np.column_stack((row[some], col[some])), n[some]
                    runs += [(int(n[i]), total + int(i)) for i in np.flatnonzero(np.diff(n, prepend=last) != 1)]
                    last, total = n[-1], total + len(n)
                    ids.write(key.tobytes())
                    came.write(val[some].tobytes())
            rows, cols = np.concatenate([r for r, _ in ys]), np.sort(np.concatenate(cs))
            order = np.argsort(rows)
            rows, yy = rows[order], np.concatenate([v for _, v in ys])[order]
            if not total:
                yield pa.RecordBatch.from_arrays([pa.array(cols), pa.array(np.zeros(len(cols)))], ["col_id", "x"])
                return
            key, came = np.memmap(f"{folder}/ids", np.int64, "r", shape=(total, 2)), np.memmap(f"{folder}/came", np.float64, "r")
            row, col = (np.memmap(f"{folder}/{k}", np.int32, "w+", shape=total) for k in ("row", "col"))
            val, done = np.memmap(f"{folder}/val", np.float64, "w+", shape=total), 0
            ends = dict(zip(starts := [r[1] for r in runs], [*starts[1:], total], strict=True))
            for _, lo in sorted(runs):
                for a in range(lo, ends[lo], CHUNK):
                    b = min(a + CHUNK, ends[lo])
                    r, k = key[a:b].T
                    row[done : done + b - a], col[done : done + b - a], val[done : done + b - a] = np.searchsorted(rows, r), np.searchsorted(cols, k), came[a:b]
                    done += b - a
            x = kernel(row, col, val, yy, len(cols))
            for a in range(0, len(cols), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(cols[a : a + (1 << 16)]), pa.array(x[a : a + (1 << 16)])], ["col_id", "x"])

    out = e.unionByName(y).unionByName(c).coalesce(1).mapInArrow(run, "col_id bigint, x double")
    return out.join(system.cols.select("col_id", "cb"), "col_id").select("cb", "col_id", "x")


def coordinate_descent(system: LinearSystem, sweeps: int = 1, order: str = "cyclic", top: float = 0.25) -> DataFrame:
    """Exact minimisation over one unknown after the other. order "last_change": every other sweep visits only
    the share ``top`` of unknowns that last moved most."""

    def kernel(row, col, val, y, n):
        x, r, last = np.zeros(n), y.copy(), np.full(n, np.inf)
        at = np.searchsorted(col, np.arange(n + 1, dtype=np.int32))
        for k in range(sweeps):
            visit = range(n) if order == "cyclic" or k % 2 == 0 else np.argsort(-last, kind="stable")[: max(1, int(top * n))]
            for j in visit:
                i, a = np.asarray(row[at[j] : at[j + 1]]), np.asarray(val[at[j] : at[j + 1]])
                d = a @ r[i] / (a @ a) if len(a) else 0.0
                x[j] += d
                r[i] -= d * a
                last[j] = abs(d)
        return x

    return _whole(system, kernel, by="col")


def _project(x: np.ndarray, steps: np.ndarray, at: np.ndarray, col, val, y: np.ndarray, norm: np.ndarray, omega: float) -> None:
    """Projects x onto the equations ``steps``, one after the other.

    Equations without a common unknown may change places, so those that wait for no earlier one go together; each still sees what all
    earlier ones with a common unknown left. Where few go together, one at a time is faster.
    """
    size = at[steps + 1] - at[steps]
    first = np.concatenate(([0], np.cumsum(size)))
    step = np.repeat(np.arange(len(steps)), size)
    place = np.arange(first[-1]) - first[step] + at[steps][step]
    c, a = np.asarray(col[place]), np.asarray(val[place])
    used, c_at = np.unique(c, return_inverse=True)
    if len(steps) < 16 * np.bincount(c_at).max():
        for k, i in enumerate(steps):
            ck, ak = c[first[k] : first[k + 1]], a[first[k] : first[k + 1]]
            x[ck] += omega * (y[i] - ak @ x[ck]) / norm[i] * ak
        return
    # entries in the order of unknowns, then steps: behind an entry is the next step that waits for its unknown
    chain = np.argsort(c_at, kind="stable")
    after = np.full(len(c), -1, np.int64)
    same = c_at[chain[:-1]] == c_at[chain[1:]]
    after[chain[:-1][same]] = step[chain[1:][same]]
    waits = size.copy()
    heads = np.ones(len(c), bool)
    heads[1:] = ~same
    np.subtract.at(waits, step[chain[heads]], 1)
    ready = np.flatnonzero(waits == 0)
    while len(ready):
        n = size[ready]
        start = np.concatenate(([0], np.cumsum(n)[:-1]))
        e = np.arange(n.sum()) - np.repeat(start - first[ready], n)
        ce, ae, i = c[e], a[e], steps[ready]
        move = omega * (y[i] - np.add.reduceat(ae * x[ce], start)) / norm[i]
        x[ce] += np.repeat(move, n) * ae
        behind = after[e]
        behind = behind[behind >= 0]
        np.subtract.at(waits, behind, 1)
        ready = np.unique(behind[waits[behind] == 0])


def kaczmarz(system: LinearSystem, sweeps: int = 1, omega: float = 1.0, randomized: bool = False, seed: int = 0) -> DataFrame:
    """Projection onto one equation after the other; randomized: rows drawn in proportion to their squared norm."""

    def kernel(row, col, val, y, n):
        x, norm = np.zeros(n), np.zeros(len(y))
        at = np.searchsorted(row, np.arange(len(y) + 1, dtype=np.int32))
        for lo in range(0, len(row), CHUNK):
            part, base = np.asarray(row[lo : lo + CHUNK]), int(row[lo])
            norm[base : int(part[-1]) + 1] += np.bincount(part - base, np.square(val[lo : lo + CHUNK]))
        some = np.flatnonzero(norm > 0)
        if not len(some):
            return x
        rng, window = np.random.default_rng(seed), max(1, CHUNK * len(some) // len(row))
        for _ in range(sweeps):
            steps = rng.choice(some, len(some), p=norm[some] / norm[some].sum()) if randomized else some
            for lo in range(0, len(steps), window):
                _project(x, steps[lo : lo + window], at, col, val, y, norm, omega)
        return x

    return _whole(system, kernel)


def normal_matrix(entries: DataFrame) -> DataFrame:
    """col_a, col_b, v: the upper triangle of A^T A, by a self-join on rows."""
    a, b = entries.select("row_id", F.col("col_id").alias("col_a"), F.col("val").alias("va")), entries.select("row_id", F.col("col_id").alias("col_b"), F.col("val").alias("vb"))
    return a.join(b, "row_id").where("col_a <= col_b").groupBy("col_a", "col_b").agg(F.sum(F.col("va") * F.col("vb")).alias("v"))


DENSE = 2500  # unknowns whose normal matrix is solved directly


def exact_least_squares(system: LinearSystem, most: int | None = None, dense: int = DENSE) -> DataFrame:
    """The least-squares solution of smallest norm: from the normal matrix up to ``dense`` unknowns, beyond by conjugate gradients from 0
    that go on until the normal equations hold to 12 digits or get no better. ValueError beyond ``most`` unknowns, if given."""
    n = system.cols.count()
    if most is not None and n > most:
        raise ValueError(f"{n} unknowns; at most {most} are solved exactly")
    spark = system.entries.sparkSession
    cols = np.sort(system.cols.select("col_id").toPandas().col_id.to_numpy())
    b = system.entries.join(system.y.select("row_id", "y"), "row_id").groupBy("col_id").agg(F.sum(F.col("val") * F.col("y")).alias("b")).toPandas()
    atb = np.zeros(n)
    atb[np.searchsorted(cols, b.col_id)] = b.b
    if n > dense:
        x = _conjugate_gradients(system.entries, cols, atb)
    else:
        m = normal_matrix(system.entries).toPandas()
        ata = np.zeros((n, n))
        i, j = np.searchsorted(cols, m.col_a), np.searchsorted(cols, m.col_b)
        ata[i, j] = ata[j, i] = m.v
        x = np.linalg.lstsq(ata, atb, rcond=None)[0]
    return spark.createDataFrame(pd.DataFrame({"col_id": cols, "x": x}), "col_id bigint, x double").join(system.cols.select("col_id", "cb"), "col_id").select("cb", "col_id", "x")


def _conjugate_gradients(entries: DataFrame, cols: np.ndarray, atb: np.ndarray, digits: float = 1e-12) -> np.ndarray:
    """x with A^T A x = A^T y. A row's entries are gathered once, so a product is one pass over rows and one sum a column; the driver holds vectors of unknowns only."""
    sc, n = entries.sparkSession.sparkContext, len(cols)
    whole = commit(entries.groupBy("row_id").agg(F.collect_list("col_id").alias("c"), F.collect_list("val").alias("v")).select("c", "v"), "by_rows")
    ids = sc.broadcast(cols)

    def product(p: np.ndarray) -> np.ndarray:
        at = sc.broadcast(p)

        def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            g = np.zeros(n)
            for batch in batches:
                if not batch.num_rows:
                    continue
                size = batch.column(0).value_lengths().to_numpy()
                col, val = np.searchsorted(ids.value, batch.column(0).flatten().to_numpy()), batch.column(1).flatten().to_numpy()
                q = np.add.reduceat(val * at.value[col], np.cumsum(size) - size)
                g += np.bincount(col, val * np.repeat(q, size), n)
            some = np.flatnonzero(g)
            yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(g[some])], ["j", "g"])

        got = whole.mapInArrow(part, "j bigint, g double").groupBy("j").agg(F.sum("g").alias("g")).toPandas()
        at.destroy()
        out = np.zeros(n)
        out[got.j.to_numpy()] = got.g
        return out

    x, r = np.zeros(n), atb.copy()
    p, rr = r.copy(), r @ r
    best, waited, enough = rr, 0, digits * digits * rr
    while rr > enough and waited < 50:
        w = product(p)
        step = rr / (p @ w)
        x, r = x + step * p, r - step * w
        rr, last = r @ r, rr
        p = r + rr / last * p
        best, waited = (rr, 0) if rr < best else (best, waited + 1)
    return x


def tile_blocks(cells: DataFrame, size: int) -> DataFrame:
    """col_id, cb: square tiles within each slice, slice by slice."""
    across = F.floor(F.col("ix") / size) + 1000 * F.floor(F.col("iy") / size)
    return cells.select("col_id", (F.col("iz") * 1_000_000 + across).cast("int").alias("cb"))


def axial_blocks(cells: DataFrame, size: int) -> DataFrame:
    """col_id, cb: lines along the axis, ``size`` x ``size`` of them together."""
    return cells.select("col_id", (F.floor(F.col("ix") / size) + 1000 * F.floor(F.col("iy") / size)).cast("int").alias("cb"))


def recut(system: LinearSystem, blocks: DataFrame) -> LinearSystem:
    """The same system with the column blocks of ``blocks`` (col_id, cb)."""
    cols = system.cols.drop("cb").join(blocks, "col_id").select("col_id", "cb", "x_true")
    return replace(system, entries=commit(system.entries.drop("cb").join(blocks, "col_id").select("cb", "rb", "row_id", "col_id", "val"), "entries"), cols=commit(cols, "cols"), density=None)


def block_descent(system: LinearSystem, sweeps: int = 1, share: float | None = None) -> DataFrame:
    """x after sweeps of exact line searches over one column block after the other. With ``share``, every second sweep visits only that share of
    the blocks, those that the sweep before moved most. Use ``recut`` with ``tile_blocks`` or ``axial_blocks`` for tiles of slices or lines along the axis."""
    x, before = commit(system.x_zero(), "x"), None
    every = sorted(r["cb"] for r in system.cols.select("cb").distinct().collect())  # block ids, not columns
    for sweep in range(sweeps):
        visit = every
        if share is not None and sweep % 2:
            visit = sorted(r["cb"] for r in most_moved_blocks(before, x, share).collect())
        before = x
        for cb in visit:  # committed block by block: the plan of a block reads the last one's files
            x = commit(col_action(system, x, [cb], "steepest"), "x")
    return x


def most_moved_blocks(before: DataFrame, after: DataFrame, share: float) -> DataFrame:
    """cb of the column blocks with the largest change, the given share of them."""
    moved = before.select("cb", "col_id", F.col("x").alias("a")).join(after.select("col_id", "x"), "col_id").groupBy("cb").agg(F.sum(F.abs(F.col("x") - F.col("a"))).alias("d"))
    return moved.withColumn("q", F.percent_rank().over(Window.orderBy(F.desc("d"), "cb"))).where(F.col("q") < share).select("cb")


def filtered_back_projection(rays: DataFrame, y: DataFrame, cells: DataFrame, shape: tuple[int, int], views: int, dets: int, pitch: float = 1.0, phase: float = 1e-3) -> DataFrame:
    """cb, col_id, x from parallel rays: the ramp filter as a join of detector cells within a view, then back-projection
    with linear interpolation."""
    line = rays.select("row_id", "view", "det").join(y.select("row_id", "y"), "row_id").select("view", "det", "y")
    k = F.col("a.det") - F.col("b.det")
    ramp = F.when(k == 0, F.lit(1 / (4 * pitch * pitch))).when(k % 2 != 0, -1 / (F.lit(np.pi**2 * pitch * pitch) * k * k)).otherwise(0.0)
    q = line.alias("a").join(line.alias("b"), F.col("a.view") == F.col("b.view")).groupBy(F.col("a.view").alias("view"), F.col("a.det").alias("det")).agg((F.sum(ramp * F.col("b.y")) * pitch).alias("q"))
    phi = F.col("view") * (np.pi / views) + phase
    x, yy = F.col("ix") + 0.5 - shape[0] / 2, F.col("iy") + 0.5 - shape[1] / 2
    at = (-x * F.sin(phi) + yy * F.cos(phi)) / pitch + (dets - 1) / 2
    views_df = rays.select("view").distinct()
    hit = cells.crossJoin(F.broadcast(views_df)).withColumn("at", at).withColumn("lo", F.floor("at").cast("int"))
    both = hit.withColumn("w", F.explode(F.array(F.struct(F.col("lo").alias("det"), (1 - (F.col("at") - F.col("lo"))).alias("w")), F.struct((F.col("lo") + 1).alias("det"), (F.col("at") - F.col("lo")).alias("w")))))
    out = both.select("cb", "col_id", "view", "w.det", F.col("w.w").alias("w")).join(q, ["view", "det"])
    return out.groupBy("cb", "col_id").agg((F.sum(F.col("w") * F.col("q")) * (np.pi / views)).alias("x"))
