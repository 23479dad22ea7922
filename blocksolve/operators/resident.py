"""Whole runs over a system held in memory, for parameter sweeps.

An experiment runs many settings on one system. Up to ``MOST`` entries (checked) the parallel axis is the setting: the system is broadcast
once, a row is a setting, and a task runs all its epochs with array operations (``sweep``). Where settings keep all tasks busy, a larger
system's entries lie in files of the shared folder instead, and a task reads a stretch of them at a time (``sweep_stored``), so that memory
holds rows and unknowns of one setting a task. Else the parallel axis is the row: every task holds the entries of its rows and all unknowns,
all settings go on together, and a round adds the tasks' shares of its gradients and step lengths through files in the shared folder
(``spread``). Draws are the same functions of (seed, epoch, block) as in ``sampling``, so all agree with ``solver.solve`` on every setting up
to rounding. What fits none goes through ``solver.solve``, one setting after the other.
"""

from __future__ import annotations

import json
import math
import os
import time
import uuid
from collections.abc import Generator, Iterator
from dataclasses import asdict, dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import BarrierTaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksolve.functions.hashing import uniform_of
from blocksolve.operators.density import all_pairs
from blocksolve.operators.sampling import draw_col_blocks, taken
from blocksolve.schema import LinearSystem, SolveSpec
from blocksolve.sources.store import commit, shared_dir

MOST = 1 << 24  # entries: 16 bytes each, so 256 MB of broadcast at most
STORED = 1 << 20  # entries beyond which many settings read them from files
SHARE = 1 << 25  # entries of one of several tasks: 512 MB
STRETCH = 1 << 17  # entries that are multiplied at once
LONG = 1 << 12  # entries of a row block that are read where they lie
LARGE = 1 << 17  # numbers from which tasks add up a slice each
OUT = "run string, kind string, epoch int, cb int, id bigint, a double, b double, c double, n bigint"


@dataclass
class Head:
    """What every task knows of a system. Columns and row blocks are numbered in the order of their ids."""

    cols: np.ndarray
    truth: np.ndarray
    within: np.ndarray  # each column's place in its block
    rbs: np.ndarray
    cbs: np.ndarray
    at: list[np.ndarray]  # places of a block's columns among all columns
    density: list[pd.DataFrame]  # place (of the row block), view, p_s, p_t, p


class Stored:
    """Numbers in a file that all tasks see; a slice of them is read when it is asked for."""

    def __init__(self, path: str, kind: type, at: int, n: int):
        self.path, self.kind, self.at, self.n = path, np.dtype(kind), at, n

    def __len__(self) -> int:
        return self.n

    def __getitem__(self, part: slice) -> np.ndarray:
        lo, hi, _ = part.indices(self.n)
        got = np.fromfile(self.path, self.kind, max(0, hi - lo), offset=self.kind.itemsize * (self.at + lo))
        if len(got) < hi - lo:
            raise OSError(f"{self.path} is too short")
        return got


@dataclass
class Block:
    """One column block: its rows in the order of row blocks, and their entries in the order of rows."""

    cb: int
    at: np.ndarray
    density: pd.DataFrame
    row: np.ndarray  # places of the rows that have entries
    start: np.ndarray  # bounds of a row's entries
    first: np.ndarray  # bounds of a row block's rows
    col: np.ndarray | Stored  # place among the block's columns
    val: np.ndarray | Stored


@dataclass
class Held:
    """A system, or a task's rows of it, as arrays. Rows are numbered in the order of their ids."""

    head: Head
    y: np.ndarray
    blocks: list[Block]


def numbers(df: DataFrame, *names: str) -> list[np.ndarray]:
    got = df.select(*names).toArrow()
    return [got[c].to_numpy() for c in names]


def _by(key: np.ndarray, *more: np.ndarray) -> tuple[np.ndarray, ...]:
    order = np.argsort(key, kind="stable")
    return key[order], *(m[order] for m in more)


def head_of(system: LinearSystem, density: DataFrame) -> Head:
    cols, cb_of, truth = _by(*numbers(system.cols, "col_id", "cb", "x_true"))
    rbs, cbs = np.unique(numbers(system.rows.select("rb").distinct(), "rb")[0]), np.unique(cb_of)
    names = ("cb", "rb", "view", "p_s", "p_t", "p")
    grid = pd.DataFrame(dict(zip(names, numbers(all_pairs(density, system.rows), *names), strict=True))).sort_values(["cb", "rb"])
    grid["place"] = np.searchsorted(rbs, grid["rb"])
    dens = dict(iter(grid.groupby("cb")))
    order, within = np.argsort(cb_of, kind="stable"), np.zeros(len(cols), np.int64)
    at = np.split(order, np.searchsorted(cb_of[order], cbs)[1:]) if len(cbs) else []
    for a in at:
        within[a] = np.arange(len(a))
    return Head(cols, truth, within, rbs, cbs, at, [dens.get(int(b), grid[:0]) for b in cbs])


def held_of(head: Head, rows: np.ndarray, y: np.ndarray, cb: np.ndarray, rb: np.ndarray, row: np.ndarray, size: np.ndarray, col: np.ndarray, val: np.ndarray) -> Held:
    """From rows and y in the order of ids, and from each column block's rows (cb, rb, row: ids in that order; size: their numbers of entries) with their entries."""
    bounds, place, blocks = np.concatenate([[0], np.cumsum(size)]), np.searchsorted(head.rbs, rb), []
    for i, b in enumerate(head.cbs):
        lo, hi = np.searchsorted(cb, [b, b + 1])
        a, z = bounds[lo], bounds[hi]
        blocks.append(Block(int(b), head.at[i], head.density[i], np.searchsorted(rows, row[lo:hi]).astype(np.int32), bounds[lo : hi + 1] - a, np.searchsorted(place[lo:hi], np.arange(len(head.rbs) + 1)), col[a:z], val[a:z]))
    return Held(head, y, blocks)


def _first(cb: np.ndarray, row: np.ndarray, before: tuple | None = None) -> np.ndarray:
    """Where a column block's next row begins."""
    new = np.append(before is None or (cb[0], row[0]) != before, (cb[1:] != cb[:-1]) | (row[1:] != row[:-1]))
    return np.flatnonzero(new)


def hold(system: LinearSystem, density: DataFrame, most: int = MOST) -> Held:
    """The system's arrays; ValueError beyond ``most`` entries, rows or columns."""
    for what, df in (("entries", system.entries), ("rows", system.y), ("columns", system.cols)):
        n = df.count()
        if n > most:
            raise ValueError(f"{n} {what}; at most {most} are held by one task")
    head = head_of(system, density)
    rows, y = _by(*numbers(system.y, "row_id", "y"))
    cb, rb, row, col, val = numbers(system.entries, "cb", "rb", "row_id", "col_id", "val")
    order = np.lexsort((col, row, rb, cb))
    cb, rb, row, col, val = (a[order] for a in (cb, rb, row, col, val))
    new = _first(cb, row) if len(cb) else np.zeros(0, np.int64)
    return held_of(head, rows, y, cb[new], rb[new], row[new], np.diff(np.append(new, len(cb))), head.within[np.searchsorted(head.cols, col)], val)


def draws(block: Block, rbs: np.ndarray, m: int, spec: SolveSpec, epoch: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of the drawn row blocks and their groups, as ``sampling.draw_row_blocks`` has them."""
    d = block.density if spec.keep_empty else block.density[block.density["p_s"] > 0]
    if not len(d):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    place, p_s, p_t, p = (d[c].to_numpy() for c in ("place", "p_s", "p_t", "p"))
    sampler = spec.sampler
    if sampler == "coin":
        sampler = "density" if uniform_of(spec.seed, epoch, "coin") < spec.coin_p else "uniform"
    w = p
    if sampler == "uniform":
        w = np.ones(len(p))
    elif sampler == "blend":
        w = (p_s + spec.theta(epoch) * (d.groupby("view")["p_s"].transform("max").to_numpy() - p_s)) / p_t
    elif sampler == "floor":
        w = np.maximum(p, spec.floor)
    u = np.array([uniform_of(spec.seed, epoch, block.cb, int(rb)) for rb in rbs[place]])
    with np.errstate(divide="ignore"):
        key = np.where(w > 0, -np.log(u) / w, np.inf)
    order = np.lexsort((place, key))[: taken(spec, m)]
    return place[order], np.arange(len(order)) // spec.group_size


def _db(num: float, den: float) -> float:
    return 10 * math.log10(num / den) if den > 0 else math.nan


def _stretches(start: np.ndarray) -> Iterator[tuple[int, int]]:
    """Runs of rows with about ``STRETCH`` entries together, or of one row with more."""
    lo = 0
    while lo < len(start) - 1:
        hi = max(lo + 1, int(np.searchsorted(start, start[lo] + STRETCH, "right")) - 1)
        yield lo, hi
        lo = hi


def _row_sums(x: np.ndarray, col: np.ndarray | Stored, val: np.ndarray | Stored, start: np.ndarray) -> np.ndarray:
    """Per row the sum of val * x[col] over its entries (one at least), a stretch of rows at a time."""
    out = np.empty(len(start) - 1)
    for lo, hi in _stretches(start):
        a, z = start[lo], start[hi]
        v = x[col[a:z]]
        v *= val[a:z]
        out[lo:hi] = np.add.reduceat(v, start[lo:hi] - a)
    return out


class Drawn:
    """The drawn row blocks of a column block. Long ones are read where they lie, one after the other; short ones are put together first."""

    def __init__(self, b: Block, place: np.ndarray, grp: np.ndarray, groups: int):
        self.b, self.width, self.groups = b, len(b.at), groups
        order = np.argsort(place)
        lo, hi, grp = b.first[place[order]], b.first[place[order] + 1], grp[order]
        self.parts = [(int(k), int(p), int(q)) for k, p, q in zip(grp, lo, hi, strict=True) if p < q]
        self.own = np.concatenate([np.arange(p, q) for _, p, q in self.parts] or [np.zeros(0, np.int64)])
        self.row_grp = np.repeat(grp, hi - lo)
        entries = int((b.start[hi] - b.start[lo]).sum())
        self.long = entries >= LONG * max(1, len(self.parts))
        if not self.long:
            cut = [slice(b.start[p], b.start[q]) for _, p, q in self.parts]
            self.col, self.val = (np.concatenate([a[c] for c in cut] or [a[:0]]) for a in (b.col, b.val))
            self.size = b.start[self.own + 1] - b.start[self.own]
            self.start = np.concatenate([[0], np.cumsum(self.size)])
            self.cell = np.repeat(self.row_grp * self.width, self.size)
            self.cell += self.col

    def back(self, r: np.ndarray) -> np.ndarray:
        """The groups' gradients, one after the other."""
        if not self.long:
            v = np.repeat(r[self.b.row[self.own]], self.size)
            v *= self.val
            return np.bincount(self.cell, v, self.groups * self.width)
        b, g = self.b, np.zeros((self.groups, self.width))
        for k, p, q in self.parts:
            for lo, hi in _stretches(b.start[p : q + 1]):
                at = b.start[p + lo : p + hi + 1]
                v = np.repeat(r[b.row[p + lo : p + hi]], np.diff(at))
                v *= b.val[at[0] : at[-1]]
                g[k] += np.bincount(b.col[at[0] : at[-1]], v, self.width)
        return g.ravel()

    def entries(self) -> np.ndarray:
        """How many entries each cell of the gradients has."""
        if not self.long:
            return np.bincount(self.cell, minlength=self.groups * self.width).astype(float)
        n = np.zeros((self.groups, self.width))
        for k, p, q in self.parts:
            for lo, hi in _stretches(self.b.start[p : q + 1]):
                n[k] += np.bincount(self.b.col[self.b.start[p + lo] : self.b.start[p + hi]], minlength=self.width)
        return n.ravel()

    def forward(self, g: np.ndarray) -> np.ndarray:
        """Each drawn row's product with its group's gradient."""
        if not self.long:
            return _row_sums(g, self.cell, self.val, self.start)
        g = g.reshape(self.groups, self.width)
        return np.concatenate([_row_sums(g[k], self.b.col, self.b.val, self.b.start[p : q + 1]) for k, p, q in self.parts])


def run(held: Held, spec: SolveSpec, checkpoints: tuple[int, ...] = ()) -> Generator:
    """Yields an array where its sum over the tasks that hold the system is to be sent back, else (kind, epoch, cb, id, a, b, c, n):
    "history" after every epoch, "x" at checkpoints and the end, "refreshes" at the end."""
    head, m, n = held.head, len(held.head.rbs), len(held.blocks)
    x, r = [np.zeros(len(b.at)) for b in held.blocks], held.y.copy()
    z, ax = ([np.zeros(len(b.row)) for b in held.blocks] for _ in range(2))  # ax: of the x that the last epoch left
    refreshes = np.zeros((n, m), np.int64)
    by_cb = {b.cb: i for i, b in enumerate(held.blocks)}
    base, last_gap, past, picks = spec.step_base, None, [], 0
    for epoch in range(1, spec.epochs + 1):
        stale = past[-spec.staleness] if spec.staleness and len(past) >= spec.staleness else None
        drawn = draw_col_blocks(sorted(by_cb), spec, epoch)
        size = {"column": 1, "epoch": max(1, len(drawn))}.get(spec.refresh, spec.refresh)
        for lo in range(0, len(drawn), size):
            together = drawn[lo : lo + size]
            damp = 1.0 / len(together) if spec.jacobi_damping == "auto" else float(spec.jacobi_damping)
            used, steps, sums = r if stale is None else stale, [], []
            for i in (by_cb[cb] for cb in together):
                b = held.blocks[i]
                place, grp = draws(b, head.rbs, m, spec, epoch)
                if not len(place):
                    continue
                picks += len(place)
                refreshes[i, place] += 1
                some = Drawn(b, place, grp, int(grp[-1]) + 1)
                sums.append(some.back(used))
                if spec.ridge:
                    sums.append(some.entries())
                steps.append((i, place, grp, some))
            if not steps:
                continue
            sums = np.split((yield np.concatenate(sums)), np.cumsum([len(a) for a in sums])[:-1])
            dens, moved = [], []
            for k, (i, _, _, some) in enumerate(steps):
                if spec.ridge:
                    g = sums[2 * k] - np.where(sums[2 * k + 1] > 0, spec.ridge * np.tile(x[i], some.groups), 0.0)
                else:
                    g = sums[k]
                ag = some.forward(g)
                dens.append(np.bincount(some.row_grp, ag * ag, some.groups))
                moved.append((g, ag))
            dens = np.split((yield np.concatenate(dens)), np.cumsum([len(a) for a in dens])[:-1])
            if spec.staleness:
                r = r.copy()  # the last one is kept
            for (i, place, grp, some), (g, ag), den in zip(steps, moved, dens, strict=True):
                b, own, groups, width = held.blocks[i], some.own, some.groups, some.width
                num = (g.reshape(groups, width) ** 2).sum(1)
                den = den + spec.ridge * num
                beta = np.full(groups, base * damp)
                if spec.step_policy != "const":
                    area = np.zeros(m)
                    area[b.density["place"]] = b.density["p_s"]
                    beta *= np.bincount(grp, area[place], groups) / b.density["p_t"].iloc[0]
                with np.errstate(divide="ignore", invalid="ignore"):
                    mu = np.where(den > 0, beta * num / den, 0.0)
                fresh = ax[i][own] + mu[some.row_grp] * ag
                if spec.residual != "true":
                    r[b.row[own]] -= fresh - z[i][own]
                z[i][own] = fresh
                x[i] = x[i] + (mu[:, None] * g.reshape(groups, width)).sum(0) / groups
            if spec.residual == "true":
                r = held.y.copy()
                for b, v in zip(held.blocks, x, strict=True):
                    r[b.row] -= _row_sums(v, b.col, b.val, b.start)
        past = [*past[-spec.staleness :], r] if spec.staleness else []
        whole, left = np.zeros(len(head.cols)), held.y.copy()
        for i, (b, v) in enumerate(zip(held.blocks, x, strict=True)):
            if b.cb in drawn:
                ax[i] = _row_sums(v, b.col, b.val, b.start)
            whole[b.at] = v
            left[b.row] -= ax[i]
        yy, ll, rr = yield np.array([held.y @ held.y, left @ left, r @ r])
        snr, gap = _db(head.truth @ head.truth, np.sum((head.truth - whole) ** 2)), _db(yy, ll)
        yield "history", epoch, None, None, snr, gap, _db(yy, rr), picks
        if spec.step_policy == "adaptive" and last_gap is not None:
            base *= 1.05 if gap > last_gap else 0.5
        stop = bool(spec.tol) and last_gap is not None and abs(gap - last_gap) < spec.tol
        if epoch in checkpoints or epoch == spec.epochs or stop:
            for b, v in zip(held.blocks, x, strict=True):
                yield "x", epoch, b.cb, head.cols[b.at], v, None, None, None
        last_gap = gap
        if stop or not math.isfinite(gap) and gap == gap:
            break
    for i, b in enumerate(held.blocks):
        place = np.flatnonzero(refreshes[i])
        yield "refreshes", epoch if spec.epochs else 0, b.cb, head.rbs[place], None, None, None, refreshes[i, place]


def batch_of(name: str, kind: str, epoch: int, *more) -> pa.RecordBatch:
    """A row, or as many as there are ids."""
    n = len(more[1]) if more[1] is not None else 1
    types = (pa.int32(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.int64())
    made = [pa.array(v, t) if isinstance(v, np.ndarray) else pa.array([v] * n, t) for v, t in zip(more, types, strict=True)]
    return pa.RecordBatch.from_arrays([pa.array([name] * n, pa.string()), pa.array([kind] * n, pa.string()), pa.array([epoch] * n, pa.int32()), *made], [f.split(" ")[0] for f in OUT.split(", ")])


def _next(one: Generator, sent: np.ndarray | None):
    try:
        return one.send(sent)
    except StopIteration:
        return None


def together(held: Held, settings: dict[str, SolveSpec], checkpoints: tuple[int, ...], add) -> Iterator[pa.RecordBatch]:
    """All settings at once, each up to its next sum; ``add`` gives the sum of an array over all tasks."""
    runs, sent = {k: run(held, s, checkpoints) for k, s in settings.items()}, {}
    while runs:
        asked = {}
        for k, one in list(runs.items()):
            out = _next(one, sent.get(k))
            while out is not None and not isinstance(out, np.ndarray):
                yield batch_of(k, *out)
                out = _next(one, None)
            if out is None:
                del runs[k]
            else:
                asked[k] = out
        if asked:
            got = add(np.concatenate(list(asked.values())))
            sent = dict(zip(asked, np.split(got, np.cumsum([len(a) for a in asked.values()])[:-1]), strict=True))


@dataclass
class Swept:
    history: DataFrame  # run, epoch, eff_epoch, snr_db, gap_db, surrogate_gap_db, picks
    x: DataFrame  # run, epoch, cb, col_id, x at checkpoints and at the end
    refreshes: DataFrame  # run, cb, rb, refreshes


def swept(out: DataFrame, grid: int) -> Swept:
    nan_null = lambda c: F.when(~F.isnan(c), F.col(c))
    h = out.where("kind = 'history'")
    return Swept(
        h.select("run", "epoch", (F.col("n") / grid).alias("eff_epoch"), nan_null("a").alias("snr_db"), nan_null("b").alias("gap_db"), nan_null("c").alias("surrogate_gap_db"), F.col("n").alias("picks")),
        out.where("kind = 'x'").select("run", "epoch", "cb", F.col("id").alias("col_id"), F.col("a").alias("x")),
        out.where("kind = 'refreshes'").select("run", "cb", F.col("id").cast("int").alias("rb"), F.col("n").alias("refreshes")),
    )


def sweep(system: LinearSystem, density: DataFrame, settings: dict[str, SolveSpec], checkpoints: tuple[int, ...] = (), most: int = MOST) -> Swept:
    """All settings side by side, a task each."""
    held = hold(system, density, most)
    return swept(side_by_side(system.entries.sparkSession, held, settings, checkpoints), len(held.head.rbs) * len(held.blocks))


def side_by_side(spark: SparkSession, system: Held | Files, settings: dict[str, SolveSpec], checkpoints: tuple[int, ...]) -> DataFrame:
    shared = spark.sparkContext.broadcast(system)
    todo = spark.createDataFrame([(i, k, json.dumps(asdict(s))) for i, (k, s) in enumerate(settings.items())], "i int, run string, spec string")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = shared.value if isinstance(shared.value, Held) else shared.value.held()
        for batch in batches:
            for name, spec in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                yield from together(held, {name: SolveSpec(**json.loads(spec))}, checkpoints, lambda a: a)

    # one setting a task
    return commit(todo.repartitionById(len(settings), F.col("i")).select("run", "spec").mapInArrow(work, OUT), "sweep")


# --- entries in files -----------------------------------------------------------------------------


@dataclass
class Files:
    """A system whose entries lie in two files, ``col`` and ``val``, in the order of column block, row block and row; a cell is a pair of blocks."""

    folder: str
    parts: int
    head: Head
    rows: np.ndarray
    y: np.ndarray
    cb: np.ndarray  # of the cells
    place: np.ndarray  # of the cells' row blocks
    at: np.ndarray  # bounds of the cells' entries
    row_at: np.ndarray  # bounds of the cells' rows

    def held(self) -> Held:
        """Rows as arrays; entries stay where they are."""
        some = [f"{self.folder}/rows-{k}" for k in range(self.parts) if os.path.exists(f"{self.folder}/rows-{k}")]
        row, start = np.concatenate([np.zeros((0, 2), np.int64), *(np.fromfile(f, np.int64).reshape(-1, 2) for f in some)]).T
        if len(row) != self.row_at[-1]:
            raise OSError(f"{self.folder} has {len(row)} of {self.row_at[-1]} rows")
        blocks = []
        for i, b in enumerate(self.head.cbs):
            lo, hi = np.searchsorted(self.cb, [b, b + 1])
            (a, z), (p, q) = self.at[[lo, hi]], self.row_at[[lo, hi]]
            first = self.row_at[lo + np.searchsorted(self.place[lo:hi], np.arange(len(self.head.rbs) + 1))] - p
            blocks.append(Block(int(b), self.head.at[i], self.head.density[i], row[p:q].astype(np.int32), np.append(start[p:q], z) - a, first, Stored(f"{self.folder}/col", np.int32, int(a), int(z - a)), Stored(f"{self.folder}/val", np.float64, int(a), int(z - a))))
        return Held(self.head, self.y, blocks)


def can_store(system: LinearSystem) -> bool:
    """Whether a task can hold what a setting has for each row, each column and each row of a column block."""
    blocks = system.cols.select("cb").distinct().count()
    return shared_path(system.entries.sparkSession) is not None and max(system.cols.count(), system.y.count() * max(1, blocks)) <= MOST


def store(system: LinearSystem, density: DataFrame, folder: str, parts: int) -> Files:
    """Writes the entries; a task writes those of consecutive cells, at their places in the files."""
    spark = system.entries.sparkSession
    head = head_of(system, density)
    rows, y = _by(*numbers(system.y, "row_id", "y"))
    cells = sorted((r["cb"], r["rb"], r["count"]) for r in system.entries.groupBy("cb", "rb").count().collect())  # block ids
    at = np.concatenate([[0], np.cumsum([n for _, _, n in cells], dtype=np.int64)])
    part = [int(a) * parts // max(1, int(at[-1])) for a in at[:-1]]
    begin = {(cb, rb): int(a) for (cb, rb, _), a in zip(cells, at[:-1], strict=True)}
    shared = spark.sparkContext.broadcast((head.cols, head.within, rows, begin))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cols, within, rows, begin = shared.value
        os.makedirs(folder, exist_ok=True)
        done, before, made, counts, k = -1, None, [], {}, 0
        # several tasks write to the two files, each at places of its own; a task that is run again writes the same
        with os.fdopen(os.open(f"{folder}/col", os.O_RDWR | os.O_CREAT), "r+b") as to_col, os.fdopen(os.open(f"{folder}/val", os.O_RDWR | os.O_CREAT), "r+b") as to_val:
            for batch in batches:
                part, cb, rb, row, col, val = (c.to_numpy() for c in batch.columns)
                if not len(cb):
                    continue
                if done < 0:
                    k, done = int(part[0]), begin[int(cb[0]), int(rb[0])]
                    to_col.seek(4 * done)
                    to_val.seek(8 * done)
                new = _first(cb, row, before)
                made.append(np.stack([np.searchsorted(rows, row[new]), new + done], 1))
                cell, n = np.unique(np.stack([cb[new], rb[new]], 1), axis=0, return_counts=True)
                for c, m in zip(map(tuple, cell.tolist()), n.tolist(), strict=True):
                    counts[c] = counts.get(c, 0) + m
                to_col.write(within[np.searchsorted(cols, col)].astype(np.int32).tobytes())
                to_val.write(val.tobytes())
                done, before = done + len(cb), (cb[-1], row[-1])
        if made:
            np.concatenate(made).astype(np.int64).tofile(mine := f"{folder}/new-{uuid.uuid4().hex}")
            os.replace(mine, f"{folder}/rows-{k}")
            yield pa.RecordBatch.from_arrays([pa.array([c[0] for c in counts], pa.int32()), pa.array([c[1] for c in counts], pa.int32()), pa.array(counts.values(), pa.int64())], ["cb", "rb", "n"])

    placed = F.broadcast(spark.createDataFrame([(cb, rb, p) for (cb, rb, _), p in zip(cells, part, strict=True)], "cb int, rb int, part int"))
    dealt = system.entries.join(placed, ["cb", "rb"]).repartitionById(parts, F.col("part")).select("part", "cb", "rb", "row_id", "col_id", "val").sortWithinPartitions("cb", "rb", "row_id", "col_id")
    n = {(r["cb"], r["rb"]): r["n"] for r in dealt.mapInArrow(work, "cb int, rb int, n bigint").collect()}  # block ids
    row_at = np.concatenate([[0], np.cumsum([n[cb, rb] for cb, rb, _ in cells], dtype=np.int64)])
    return Files(folder, parts, head, rows, y, np.array([c[0] for c in cells], np.int64), np.searchsorted(head.rbs, [c[1] for c in cells]), at, row_at)


def sweep_stored(system: LinearSystem, density: DataFrame, settings: dict[str, SolveSpec], checkpoints: tuple[int, ...] = ()) -> Swept:
    """All settings side by side, a task each, over entries in files of the shared folder."""
    spark = system.entries.sparkSession
    folder = f"{shared_path(spark)}/stored-{uuid.uuid4().hex}"
    files = store(system, density, folder, 4 * spark.sparkContext.defaultParallelism)
    out = side_by_side(spark, files, settings, checkpoints)
    fs = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs.getFileSystem(spark._jsc.hadoopConfiguration()).delete(fs, True)
    return swept(out, len(files.head.rbs) * len(files.head.cbs))


# --- a share of the rows in every task ------------------------------------------------------------


def shared_path(spark: SparkSession) -> str | None:
    """The shared folder as a path of the file system; None if it is none."""
    at = shared_dir(spark)
    if at.startswith("file:"):
        at = "/" + at[5:].lstrip("/")
    return at if at.startswith("/") else None


def can_spread(system: LinearSystem, share: int = SHARE) -> bool:
    spark = system.entries.sparkSession
    tasks = spark.sparkContext.defaultParallelism
    return shared_path(spark) is not None and system.cols.count() <= MOST and max(system.entries.count(), system.y.count()) <= tasks * share


class Sums:
    """Sums over tasks through files: each writes its array and waits for those of the others. All tasks add in the same order, so all get the same numbers."""

    def __init__(self, folder: str, me: int, of: int):
        self.folder, self.me, self.of, self.turn = folder, me, of, 0
        os.makedirs(folder, exist_ok=True)

    def put(self, a: np.ndarray) -> None:
        self.turn += 1
        a.tofile(f"{self.folder}/{self.me}-new")
        os.rename(f"{self.folder}/{self.me}-new", f"{self.folder}/{self.me}-{self.turn}")
        # whoever reads this turn has read the last but one
        if self.turn > 2:
            os.remove(f"{self.folder}/{self.me}-{self.turn - 2}")

    def get(self, task: int, lo: int = 0, hi: int = -1) -> np.ndarray:
        path, wait = f"{self.folder}/{task}-{self.turn}", 1e-4
        while True:
            try:
                return np.fromfile(path, np.float64, hi - lo if hi >= 0 else -1, offset=8 * lo)
            except FileNotFoundError:
                time.sleep(wait)
                wait = min(2 * wait, 2e-3)

    def add(self, a: np.ndarray) -> np.ndarray:
        self.put(a)
        if len(a) < LARGE:
            return sum(self.get(k) for k in range(self.of))
        lo, hi = len(a) * self.me // self.of, len(a) * (self.me + 1) // self.of
        mine = self.get(0, lo, hi)
        for k in range(1, self.of):
            mine += self.get(k, lo, hi)
        self.put(mine)
        return np.concatenate([self.get(k) for k in range(self.of)])


def shares(system: LinearSystem, tasks: int) -> DataFrame:
    """task, kind (0: an observation, 1: an entry), cb, rb, row_id, col_id, val. A task gets whole row blocks; large ones are dealt out by row."""
    spark = system.entries.sparkSession
    sizes = {r["rb"]: r["count"] for r in system.entries.groupBy("rb").count().collect()}  # block ids
    whole, load, to = sum(sizes.values()), [0] * tasks, []
    for rb, n in sorted(sizes.items(), key=lambda kv: (-kv[1], kv[0])):
        if 4 * tasks * n > whole:
            continue
        k = min(range(tasks), key=load.__getitem__)
        load[k] += n
        to.append((rb, k))
    placed = F.broadcast(spark.createDataFrame(to, "rb int, task int"))
    y = system.y.select(F.lit(0).cast("byte").alias("kind"), F.lit(0).alias("cb"), "rb", "row_id", F.lit(0).cast("bigint").alias("col_id"), F.col("y").alias("val"))
    both = y.unionByName(system.entries.select(F.lit(1).cast("byte").alias("kind"), "cb", "rb", "row_id", "col_id", "val"))
    return both.join(placed, "rb", "left").withColumn("task", F.coalesce("task", F.pmod(F.hash("row_id"), F.lit(tasks))))


def spread(system: LinearSystem, density: DataFrame, settings: dict[str, SolveSpec], checkpoints: tuple[int, ...] = (), tasks: int | None = None) -> Swept:
    """All settings together over rows that are dealt out to ``tasks`` (all cores), which run at the same time."""
    spark = system.entries.sparkSession
    tasks = tasks or spark.sparkContext.defaultParallelism
    head, folder = head_of(system, density), f"{shared_path(spark)}/sums-{uuid.uuid4().hex}"
    shared, specs = spark.sparkContext.broadcast(head), {k: asdict(s) for k, s in settings.items()}

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        context, head = BarrierTaskContext.get(), shared.value
        ys, keys, cols, vals, total, before = [], [], [], [], 0, None
        for batch in batches:
            kind, cb, rb, row, col, val = (c.to_numpy() for c in batch.columns)
            a = int(np.searchsorted(kind, 1))
            ys.append((row[:a].copy(), val[:a].copy()))
            if a == len(kind):
                continue
            cb, rb, row = cb[a:], rb[a:], row[a:]
            new = _first(cb, row, before)
            keys.append((cb[new], rb[new], row[new], new + total))
            cols.append(head.within[np.searchsorted(head.cols, col[a:])])
            vals.append(val[a:].copy())
            total, before = total + len(cb), (cb[-1], row[-1])
        rows, y = _by(*map(np.concatenate, zip(*ys, strict=True))) if ys else (np.zeros(0, np.int64), np.zeros(0))
        cb, rb, row, at = map(np.concatenate, zip(*keys, strict=True)) if keys else (np.zeros(0, np.int64) for _ in range(4))
        col, val = (np.concatenate(cols), np.concatenate(vals)) if keys else (np.zeros(0, np.int64), np.zeros(0))
        del ys, keys, cols, vals
        held = held_of(head, rows, y, cb, rb, row, np.diff(np.append(at, total)), col, val)
        me = context.partitionId()
        sums = Sums(f"{folder}/{context.allGather(uuid.uuid4().hex)[0]}", me, tasks)  # a folder for each attempt
        for out in together(held, {k: SolveSpec(**s) for k, s in specs.items()}, checkpoints, sums.add):
            if me == 0:
                yield out

    dealt = shares(system, tasks).repartitionById(tasks, F.col("task")).select("kind", "cb", "rb", "row_id", "col_id", "val").sortWithinPartitions("kind", "cb", "rb", "row_id", "col_id")
    out = commit(dealt.mapInArrow(work, OUT, barrier=True).repartition(1), "sweep")  # a stage that is shuffled starts anew if a task fails
    fs = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs.getFileSystem(spark._jsc.hadoopConfiguration()).delete(fs, True)
    return swept(out, len(head.rbs) * len(head.cbs))
