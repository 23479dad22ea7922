"""Averaged block descent and its sampled and grouped forms.

An epoch visits the drawn column blocks, ``refresh`` of them against one residual. In a round every picked group makes
one block step from the same x and r; the mean of the proposals becomes x and the stored projections give the next residual.
State (x and z by column block, r, the picks) is committed to the shared folder between rounds; a round reads it back, so plans
stay short and a lost executor costs one round.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksolve.operators import density as dens
from blocksolve.operators import measures, packed, sampling, step
from blocksolve.schema import PICKS, X, Z, LinearSystem, SolveSpec
from blocksolve.sources.store import Parts, commit, forget

HISTORY = "run string, epoch int, eff_epoch double, snr_db double, gap_db double, surrogate_gap_db double, picks bigint"


@dataclass
class State:
    x: DataFrame
    z: DataFrame
    r: DataFrame


@dataclass
class SolveResult:
    x: DataFrame
    history: DataFrame
    picks_log: DataFrame
    state: State


def start(system: LinearSystem) -> State:
    """x = 0, no projections, r = y."""
    z = system.y.select(F.lit(0).alias("cb"), "rb", "row_id", F.lit(0.0).alias("z")).where("false")
    return State(system.x_zero(), z, system.y.select("rb", "row_id", F.col("y").alias("r")))


def damping(spec: SolveSpec, together: int) -> float:
    """Blocks that correct one residual together overshoot like a Jacobi sweep, so their steps are divided by their number."""
    return 1.0 / together if spec.jacobi_damping == "auto" else float(spec.jacobi_damping)


def steps_of(
    system: LinearSystem, x: DataFrame, r: DataFrame, picks: DataFrame, spec: SolveSpec, together: int, base: float | None = None, keep: Callable[[DataFrame, str], DataFrame] = lambda df, name: df
) -> tuple[DataFrame, DataFrame]:
    """The block steps of ``picks`` (cb, rb, grp, p_s, p_t) against r: the new x, and the picked blocks' projections.

    ``keep`` holds what several results need (gradients, projections); as given, the steps are one lazy plan.
    """
    beta = sampling.relaxation(picks, spec, damping(spec, together), base)
    visits = sampling.visits(picks)
    if spec.strategy == "packed":
        if spec.ridge:
            raise ValueError("the packed kernel has no ridge term")
        blocks = system.entries if "at" in system.entries.columns else packed.pack(system.entries)
        joined = blocks.join(picks.select("cb", "rb", "grp"), ["cb", "rb"]).join(packed.slices(r, "rb", "row_id", "r"), "rb").join(packed.slices(x, "cb", "col_id", "x"), "cb")
        if spec.group_size == 1:
            out = keep(packed.step_single(joined.join(beta, ["cb", "grp"])), "steps")
            move = out.select("cb", F.explode(F.arrays_zip("cols", "move")).alias("e")).groupBy("cb", F.col("e.cols").alias("col_id")).agg(F.sum("e.move").alias("move"))
            fresh = out.select("cb", "rb", F.explode(F.arrays_zip("rows", "z")).alias("e")).select("cb", "rb", F.col("e.rows").alias("row_id"), F.col("e.z").alias("z"))
        else:
            move, fresh = packed.step_grouped(joined, beta, keep)
        moved = x.join(move, ["cb", "col_id"], "left").join(visits, "cb", "left").select("cb", "col_id", (F.col("x") + F.coalesce(F.col("move") / F.col("visits"), F.lit(0.0))).alias("x"))
        return moved, fresh
    active = step.activate(system.entries, picks)
    xg = keep(step.with_x(step.back_project(active, r), x, spec.ridge), "gradients")
    f = keep(step.forward_pair(active, xg), "projections")
    mu = step.step_length(xg, f, beta, spec.ridge)
    return step.average(x, xg, mu, visits), step.partial_projections(f, mu)


def residual_of(system: LinearSystem, x: DataFrame, z: DataFrame, spec: SolveSpec) -> DataFrame:
    return step.true_residual(packed.unpack(system.entries), system.y, x) if spec.residual == "true" else step.surrogate_residual(system.y, z)


def round_of(system: LinearSystem, state: State, picks: DataFrame, spec: SolveSpec, together: int) -> State:
    """One round over ``picks``, from state to state, as one lazy plan."""
    x, fresh = steps_of(system, state.x, state.r, picks, spec, together)
    z = step.merge_z(state.z, fresh, picks)
    return State(x, z, residual_of(system, x, z, spec))


def rounds(blocks: list[int], refresh: str | int) -> Iterator[list[int]]:
    size = {"column": 1, "epoch": max(1, len(blocks))}.get(refresh, refresh)
    for i in range(0, len(blocks), size):
        yield blocks[i : i + size]


def density_of(system: LinearSystem) -> DataFrame:
    return system.density if system.density is not None else dens.entry_density(system.entries, system.rows)


def epochs_lazily(system: LinearSystem, spec: SolveSpec, n_rows: int, col_blocks: list[int]) -> State:
    """A few epochs without measures. One round is one plan; x and z are committed between rounds, as each round's plan uses the
    last state several times and would double with every round."""
    state, d, done = start(system), density_of(system), 0
    for epoch in range(1, spec.epochs + 1):
        drawn = sampling.draw_col_blocks(col_blocks, spec, epoch)
        for cbs in rounds(drawn, spec.refresh):
            picks = sampling.draw_row_blocks(d, system.rows, n_rows, spec, epoch, cbs)
            if done:
                x, z = commit(state.x, "x"), commit(state.z, "z")
                state = State(x, z, residual_of(system, x, z, spec))
                d = commit(d, "density") if done == 1 else d
            state = round_of(system, state, picks, spec, len(cbs))
            done += 1
    return state


def solve(system: LinearSystem, spec: SolveSpec, run: str = "run", measure_every: int = 1, x_true: bool = True) -> SolveResult:
    """All epochs, committed round by round. The driver reads one row of measures an epoch, and nothing that grows with the data.

    x and z are kept by column block: a round draws its picks once, rewrites the blocks that it visits and updates the residual
    of the rows that they touch. Every plan reads the last round's files only, so the last round costs what the first did.
    """
    spark: SparkSession = system.entries.sparkSession
    system = replace(system, entries=commit(system.entries.repartition("cb", "rb"), "entries"), y=commit(system.y, "y"), rows=commit(system.rows, "rows"), cols=commit(system.cols, "cols"))
    d = commit(density_of(system), "density")
    plain = system
    if spec.strategy == "packed":
        system = replace(system, entries=commit(packed.pack(system.entries), "packed"))
    col_blocks = sorted(r["cb"] for r in system.cols.select("cb").distinct().collect())  # block ids, not columns
    m, n = system.rows.select("rb").distinct().count(), len(col_blocks)
    x, z, log = Parts(spark, "x", X), Parts(spark, "z", Z), Parts(spark, "picks", PICKS + ", p_s double, p_t double")
    x.write(plain.x_zero(), col_blocks)
    r = plain.y.select("rb", "row_id", F.col("y").alias("r"))  # the observations, then a file a round
    log_of = lambda: spark.read.schema(PICKS).option("recursiveFileLookup", "true").parquet(log.root)
    past, base, last_gap, history, whole = [], spec.step_base, None, [], 0
    for epoch in range(1, spec.epochs + 1):
        stale = past[-spec.staleness] if spec.staleness and len(past) >= spec.staleness else None
        for cbs in rounds(sampling.draw_col_blocks(col_blocks, spec, epoch), spec.refresh):
            log.write(sampling.draw_row_blocks(d, system.rows, m, spec, epoch, cbs).select("epoch", "cb", "rb", "pick_rank", "grp", "p_s", "p_t"), cbs)
            picks = log.read(cbs)
            made: list[DataFrame] = []

            def hold(df: DataFrame, name: str, made: list = made) -> DataFrame:
                made.append(commit(df, name))
                return made[-1]

            moved, fresh = steps_of(system, x.read(cbs), r if stale is None else stale, picks, spec, len(cbs), base, hold)
            before = z.read(cbs)
            was = before.join(picks.select("cb", "rb"), ["cb", "rb"], "left_semi")
            old = x.write(moved, cbs) + z.write(step.merge_z(before, fresh, picks), cbs)
            if spec.residual == "true":
                new = commit(step.true_residual(plain.entries, plain.y, x.read()), "r")
            else:
                new = commit(step.surrogate_residual_touched(r, was, fresh, picks), "r")
            for df in [*made, *([r] if whole and not any(r is p for p in past) else [])]:
                forget(df)
            x.drop(old)
            r, whole = new, whole + 1
        if spec.staleness:
            past.append(r)
            for df in past[: -spec.staleness]:
                forget(df)
            past = past[-spec.staleness :]
        if epoch % measure_every == 0 or epoch == spec.epochs:
            snr = measures.snr_db(plain.x_true(), x.read()) if x_true else spark.range(1).select(F.lit(None).cast("double").alias("snr_db"))
            drawn = log_of().count()
            row = snr.crossJoin(measures.gap_db(plain.entries, x.read(), plain.y)).crossJoin(measures.surrogate_gap_db(plain.y, r).withColumnRenamed("gap_db", "surrogate_gap_db")).first()
            history.append((run, epoch, drawn / (m * n), row["snr_db"], row["gap_db"], row["surrogate_gap_db"], drawn))
            gap = row["gap_db"]
            if spec.step_policy == "adaptive" and gap is not None and last_gap is not None:
                base = base * (1.05 if gap > last_gap else 0.5)
            if spec.tol and gap is not None and last_gap is not None and abs(gap - last_gap) < spec.tol:
                break
            last_gap = gap
    picked = log_of() if whole else spark.createDataFrame([], PICKS)
    return SolveResult(x.read(), spark.createDataFrame(history, HISTORY), picked, State(x.read(), z.read(), r))


def repeat_runs(system: LinearSystem, spec: SolveSpec, seeds: list[int], run: str = "run") -> DataFrame:
    """The histories of one run per seed, one under the other."""
    out = None
    for s in seeds:
        h = solve(system, replace(spec, seed=s), f"{run}-{s}").history
        out = h if out is None else out.unionByName(h)
    return out
