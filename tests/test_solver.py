"""The hand-worked system, equivalences of variants, sampling laws, geometry and storage."""

import math
import os
from collections import Counter
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from blocksolve.functions import geometry
from blocksolve.functions.hashing import uniform, uniform_of
from blocksolve.operators import baselines, measures, resident, sampling, solver, step
from blocksolve.operators import density as dens
from blocksolve.plans import blocks
from blocksolve.schema import SolveSpec, validate
from blocksolve.sources import store, systems


@pytest.fixture(scope="module")
def f1(spark):
    return systems.f1(spark)


def values(x):
    return [r["x"] for r in x.orderBy("col_id").collect()]


@pytest.mark.parametrize("strategy", ["relational", "packed"])
def test_hand_worked_epochs(f1, strategy):
    r = solver.solve(f1, SolveSpec(epochs=3, strategy=strategy))
    h = [tuple(x) for x in r.history.orderBy("epoch").select("snr_db", "gap_db", "surrogate_gap_db").collect()]
    assert h[0][2] is None
    assert np.allclose([x[:2] for x in h], [(3.716111, 6.434527), (5.860719, 8.117428), (23.802112, 29.444827)], atol=1e-5)
    assert np.allclose([h[1][2], h[2][2]], [5.553166, 13.675657], atol=1e-5)
    assert values(r.x) == pytest.approx([1, 2, 13 / 4, 15 / 4])


@pytest.mark.parametrize("strategy", ["relational", "packed"])
def test_one_residual_for_all_blocks_overshoots_unless_damped(f1, strategy):
    r = solver.solve(f1, SolveSpec(epochs=2, refresh="epoch", jacobi_damping=1.0, strategy=strategy))
    assert values(r.x) == pytest.approx([3 / 4, 3 / 4, 7 / 4, 7 / 4])
    damped = solver.solve(f1, SolveSpec(epochs=1, refresh="epoch", strategy=strategy), measure_every=1)
    assert damped.history.first()["gap_db"] == pytest.approx(9.902, abs=1e-3)


@pytest.mark.parametrize("strategy", ["relational", "packed"])
def test_grouped_step(f1, strategy):
    x = solver.epochs_lazily(f1, SolveSpec(group_size=2, strategy=strategy), 2, [0]).x
    assert values(x)[:2] == pytest.approx([455 / 193, 585 / 193])


def test_all_samplers_agree_when_everything_is_drawn(f1):
    want = values(solver.epochs_lazily(f1, SolveSpec(), 2, [0, 1]).x)
    for sampler in ("uniform", "blend", "coin", "floor"):
        assert values(solver.epochs_lazily(f1, SolveSpec(sampler=sampler, floor=0.1), 2, [0, 1]).x) == pytest.approx(want)


def test_runs_stop_when_the_gap_stands_still(f1):
    assert solver.solve(f1, SolveSpec(epochs=9, tol=50.0, refresh=2)).history.count() == 2


SPECS = {
    "blend": SolveSpec(epochs=2, sampler="blend", theta_step=0.8, row_fraction=0.5, last_group="full", group_size=2, step_policy="area", step_base=3.0),
    "true": SolveSpec(epochs=2, residual="true", row_fraction=0.75, refresh="epoch", group_size=2, strategy="packed"),
    "stale": SolveSpec(epochs=3, staleness=1, refresh="epoch", ridge=0.5, sampler="coin", seed=3),
    "adaptive": SolveSpec(epochs=3, step_policy="adaptive", step_base=6.0, sampler="floor", floor=0.3, row_fraction=0.5, keep_empty=True, refresh="epoch"),
    "columns": SolveSpec(epochs=2, sampler="uniform", col_fraction=0.5, row_fraction=0.5),
}


@pytest.fixture(scope="module")
def grid(spark, tables):
    """Orders by ship days, coarse; every second row block is another view."""
    s = systems.assemble(systems.supplier(spark, tables))
    s = replace(s, rows=s.rows.withColumn("view", F.floor(F.col("rb") / 2).cast("int")))
    return replace(s, entries=store.commit(s.entries, "entries"), y=store.commit(s.y, "y"), rows=store.commit(s.rows, "rows"), cols=store.commit(s.cols, "cols"))


@pytest.fixture(scope="module")
def swept(grid):
    return resident.sweep(grid, solver.density_of(grid), SPECS, (1,))


@pytest.mark.parametrize("name", SPECS)
def test_a_run_in_one_task_equals_the_distributed_run(grid, swept, name):
    spec = SPECS[name]
    mine = swept.history.where(F.col("run") == name).orderBy("epoch").toPandas()
    x = swept.x.where((F.col("run") == name) & (F.col("epoch") == spec.epochs)).orderBy("col_id").toPandas()
    r = solver.solve(grid, spec)
    h = r.history.orderBy("epoch").toPandas()
    assert list(mine["picks"]) == list(h["picks"]) and r.picks_log.count() == h["picks"].iloc[-1]
    for c in ("eff_epoch", "snr_db", "gap_db", "surrogate_gap_db"):
        assert np.allclose(mine[c].astype(float), h[c].astype(float), rtol=1e-9, atol=1e-7, equal_nan=True), (name, c)
    assert np.allclose(x["x"], r.x.orderBy("col_id").toPandas()["x"])
    if spec.residual == "surrogate":
        again = step.surrogate_residual(grid.y, r.state.z).select("row_id", F.col("r").alias("r2"))
        assert r.state.r.join(again, "row_id").where("abs(r - r2) > 1e-6 * (1 + abs(r2))").count() == 0


def test_sweeps_refuse_large_systems(grid):
    with pytest.raises(ValueError, match="held by one task"):
        resident.sweep(grid, solver.density_of(grid), {"a": SolveSpec()}, most=100)


def test_runs_spread_over_tasks_equal_runs_in_one_task(grid, swept):
    """Rows dealt out: two row blocks of four tasks' rows, the others whole."""
    by = ["run", "epoch"]
    spread = resident.spread(grid, solver.density_of(grid), SPECS, (1,))
    a, b = (s.history.orderBy(*by).toPandas() for s in (spread, swept))
    assert len(a) == len(b) and np.allclose(a.drop(columns="run").astype(float), b.drop(columns="run").astype(float), rtol=1e-9, atol=1e-7, equal_nan=True)
    a, b = (s.x.orderBy(*by, "col_id").toPandas() for s in (spread, swept))
    assert len(a) == len(b) and np.allclose(a["x"], b["x"])
    a, b = (s.refreshes.orderBy("run", "cb", "rb").toPandas() for s in (spread, swept))
    assert a.equals(b)


def test_whole_row_blocks_go_to_one_task(spark, tables):
    s = systems.assemble(systems.basket(spark, tables, 72, 4))
    per = resident.shares(s, 4).groupBy("rb").agg(F.countDistinct("task").alias("tasks"), F.count("*").alias("n")).toPandas()
    assert set(per["tasks"]) == {1} and per["n"].sum() == s.y.count() + s.entries.count()
    rows = resident.shares(s, 1).where("kind = 0").count()
    assert rows == s.y.count()


def test_sums_of_tasks_by_slices(tmp_path):
    from concurrent.futures import ThreadPoolExecutor

    rng = np.random.default_rng(1)
    parts = [[rng.normal(size=n) for n in (3, resident.LARGE + 5, 2, resident.LARGE + 1)] for _ in range(3)]

    def one(k):
        sums = resident.Sums(str(tmp_path / "s"), k, 3)
        return [sums.add(a) for a in parts[k]]

    with ThreadPoolExecutor(3) as pool:
        got = list(pool.map(one, range(3)))
    for g in got:
        for k in range(4):
            assert np.array_equal(g[k], parts[0][k] + parts[1][k] + parts[2][k])


def test_long_row_blocks_equal_short_ones(grid, monkeypatch):
    """Entries read where they lie, a few at a time, or put together."""
    held, got = resident.hold(grid, solver.density_of(grid)), []
    for long, stretch in ((1, 5), (1 << 40, 1 << 17)):
        monkeypatch.setattr(resident, "LONG", long)
        monkeypatch.setattr(resident, "STRETCH", stretch)
        got.append([b.to_pydict() for b in resident.together(held, SPECS, (), lambda a: a)])
    for a, b in zip(*got, strict=True):
        for c in a:
            same = a[c] == b[c] if c not in "abc" else np.allclose(np.array(a[c], float), np.array(b[c], float), rtol=1e-9, atol=1e-7, equal_nan=True)
            assert same, (c, a["run"])


def test_systems_beyond_one_task_are_spread(grid, monkeypatch):
    """Before, they went setting by setting through the distributed solver."""
    from blocksolve.plans import workloads

    monkeypatch.setattr(resident, "MOST", 1000)
    monkeypatch.setattr(solver, "solve", None)
    h = workloads.run_all(grid, {"a": SolveSpec(epochs=2), "b": SolveSpec(epochs=3)}).history
    assert h.count() == 5


def test_many_settings_read_entries_from_files(grid, swept, monkeypatch):
    """Before, beyond one task every task held its entries and the states of all settings."""
    from blocksolve.plans import workloads

    monkeypatch.setattr(resident, "STORED", 100)
    monkeypatch.setattr(resident, "spread", None)
    monkeypatch.setattr(resident, "hold", None)
    by, got = ["run", "epoch"], workloads.run_all(grid, SPECS, (1,))
    a, b = (s.history.orderBy(*by).toPandas() for s in (got, swept))
    assert len(a) == len(b) and np.allclose(a.drop(columns="run").astype(float), b.drop(columns="run").astype(float), rtol=1e-9, atol=1e-7, equal_nan=True)
    a, b = (s.x.orderBy(*by, "col_id").toPandas() for s in (got, swept))
    assert len(a) == len(b) and np.allclose(a["x"], b["x"])
    a, b = (s.refreshes.orderBy("run", "cb", "rb").toPandas() for s in (got, swept))
    assert a.equals(b)


def test_stored_entries_equal_held_ones(grid, tmp_path, monkeypatch):
    """Cells in several parts; runs read them a few at a time, or put together."""
    density = solver.density_of(grid)
    want, files = resident.hold(grid, density), resident.store(grid, density, str(tmp_path / "s"), 5)
    got = files.held()
    assert np.array_equal(got.y, want.y)
    for a, b in zip(got.blocks, want.blocks, strict=True):
        assert isinstance(a.col, resident.Stored) and len(a.val) == len(b.val) > 9
        for name in ("row", "start", "first"):
            assert np.array_equal(getattr(a, name), getattr(b, name)), name
        assert np.array_equal(a.col[:], b.col) and np.array_equal(a.val[3:9], b.val[3:9]) and not len(a.val[:0])
    for long, stretch in ((1, 50), (1 << 40, 1 << 17)):
        monkeypatch.setattr(resident, "LONG", long)
        monkeypatch.setattr(resident, "STRETCH", stretch)
        for a, b in zip(*(resident.together(h, SPECS, (), lambda a: a) for h in (got, want)), strict=True):
            assert a.equals(b)
    os.truncate(tmp_path / "s" / "val", 8)
    with pytest.raises(OSError, match="too short"):
        got.blocks[-1].val[:]


def test_schedules():
    assert [SolveSpec(theta_step=0.4).theta(e) for e in (1, 2, 3, 4)] == [0.0, 0.4, 0.8, 1.0]


def test_adaptive_steps_keep_the_share_of_the_area(grid):
    d = solver.density_of(grid)
    picks = sampling.draw_row_blocks(d, grid.rows, 4, SolveSpec(), 1)
    adaptive, area = (sampling.relaxation(picks, SolveSpec(step_policy=p, step_base=3.0), base=2.0).orderBy("cb", "grp").collect() for p in ("adaptive", "area"))
    assert adaptive == area and len({r["beta"] for r in area}) > 1


def test_packed_rounds_honour_the_true_residual(f1):
    a, b = (values(solver.epochs_lazily(f1, SolveSpec(epochs=3, residual="true", refresh="epoch", strategy=k), 2, [0, 1]).x) for k in ("relational", "packed"))
    assert a == pytest.approx(b)


def test_plans_do_not_grow_with_the_epochs(f1):
    def size(epochs):
        st = solver.solve(f1, SolveSpec(epochs=epochs), measure_every=epochs).state
        return [len(df._jdf.queryExecution().optimizedPlan().toString().splitlines()) for df in (st.x, st.z, st.r)]

    assert size(2) == size(4)


def test_ridge_shrinks(f1):
    plain, ridge = (np.array(values(solver.epochs_lazily(f1, SolveSpec(epochs=2, ridge=k), 2, [0, 1]).x)) for k in (0.0, 2.0))
    assert np.linalg.norm(ridge) < np.linalg.norm(plain)


def test_bad_settings_are_refused(f1, spark):
    for how in ({"row_fraction": 0}, {"col_fraction": 2}, {"group_size": 0}, {"step_base": 0}, {"sampler": "?"}, {"step_policy": "?"}, {"residual": "?"}):
        with pytest.raises(ValueError):
            SolveSpec(**how)
    validate(f1)
    with pytest.raises(ValueError, match="several"):
        validate(replace(f1, rows=f1.rows.unionByName(f1.rows)))
    with pytest.raises(ValueError, match="no entries"):
        validate(replace(f1, entries=f1.entries.where("false")))
    with pytest.raises(ValueError, match="finite"):
        validate(replace(f1, entries=f1.entries.withColumn("val", F.lit(float("inf")))))


def test_draws_follow_the_density(spark):
    d = dens.with_shares(spark.createDataFrame([(0, rb, rb, float(w)) for rb, w in enumerate((1, 2, 3, 4))], "cb int, rb int, view int, p_s double"))
    rows = d.select("rb").withColumns({"row_id": F.col("rb").cast("bigint"), "view": F.col("rb"), "sub": F.lit(0)})
    first = Counter()
    n = 2000
    got = spark.range(n).crossJoin(d).withColumn("key", -F.log(uniform(0, F.col("id"), F.col("cb"), F.col("rb"))) / F.col("p")).groupBy("id").agg(F.min_by("rb", "key").alias("rb"))
    first.update(r["rb"] for r in got.collect())
    chi = sum((first[rb] - n * w / 10) ** 2 / (n * w / 10) for rb, w in enumerate((1, 2, 3, 4)))
    assert chi < 16.3
    picks = sampling.draw_row_blocks(d, rows, 4, SolveSpec(row_fraction=0.5, group_size=2), 1).collect()
    assert sorted(p["pick_rank"] for p in picks) == [1, 2] and {p["grp"] for p in picks} == {0}
    assert [p["rb"] for p in picks] == [p["rb"] for p in sampling.draw_row_blocks(d.repartition(3), rows, 4, SolveSpec(row_fraction=0.5, group_size=2), 1).collect()]


def test_blend_at_its_ends(spark):
    d = dens.with_shares(spark.createDataFrame([(0, 0, 0, 1.0), (0, 1, 0, 3.0), (0, 2, 1, 2.0)], "cb int, rb int, view int, p_s double"))
    assert [r["w"] for r in dens.blended(d, 0.0).orderBy("rb").collect()] == pytest.approx([1 / 6, 3 / 6, 2 / 6])
    assert [r["w"] for r in dens.blended(d, 1.0).orderBy("rb").collect()] == pytest.approx([3 / 6, 3 / 6, 2 / 6])


def test_uniform_is_the_same_on_the_driver(spark):
    assert spark.range(1).select(uniform(3, F.lit(5), "a")).first()[0] == uniform_of(3, 5, "a")


def test_exact_solution_and_baselines(f1, spark):
    x = baselines.exact_least_squares(f1)

    def gap(x):
        found = measures.gap_db(f1.entries, x, f1.y).first()[0]
        return math.inf if found is None else found  # null: no error at all

    assert gap(x) > 200
    for got in (baselines.coordinate_descent(f1, 30), baselines.coordinate_descent(f1, 40, "last_change"), baselines.kaczmarz(f1, 60), baselines.kaczmarz(f1, 60, randomized=True)):
        assert gap(got) > 40
    with pytest.raises(ValueError):
        baselines.exact_least_squares(f1, 3)
    moved = baselines.most_moved_blocks(f1.x_zero(), f1.x_true(), 0.5)
    assert [r["cb"] for r in moved.collect()] == [1]


def test_tiles_and_lines_partition_a_volume(spark):
    grid = geometry.cells(spark, (4, 4, 2), (2, 2, 1))
    assert baselines.tile_blocks(grid, 2).select("cb").distinct().count() == 8
    assert baselines.axial_blocks(grid, 2).select("cb").distinct().count() == 4


def steepest(entries, y, blocks, sweeps, share=None):
    """Exact line searches over one column block after the other, in plain arrays. ``blocks``: col_id -> block."""
    rows, cols = sorted(y), sorted(blocks)
    a = np.zeros((len(rows), len(cols)))
    for r, c, v in entries:
        a[rows.index(r), cols.index(c)] = v
    x, obs, of = np.zeros(len(cols)), np.array([y[r] for r in rows]), np.array([blocks[c] for c in cols])
    every, moved = sorted(set(of)), {}
    for sweep in range(sweeps):
        visit, before = every, x.copy()
        if share is not None and sweep % 2:
            order = sorted(every, key=lambda b: (-moved[b], b))
            visit = sorted(b for i, b in enumerate(order) if i / (len(every) - 1) < share)
        for b in visit:
            g = np.where(of == b, a.T @ (obs - a @ x), 0.0)
            ag = a @ g
            x = x + (g @ g) / (ag @ ag) * g if ag @ ag > 0 else x
        moved = {b: np.abs(x - before)[of == b].sum() for b in every}
    return dict(zip(cols, x, strict=True))


def test_block_descents_equal_plain_arrays(spark):
    s, cells = blocks.volume(spark)
    entries = [tuple(r) for r in s.entries.select("row_id", "col_id", "val").collect()]
    y = {r["row_id"]: r["y"] for r in s.y.collect()}
    for name, part, sweeps, share in (("base_slice_tiles", baselines.tile_blocks(cells, 4), 1, None), ("base_axial_topchange", baselines.axial_blocks(cells, 2), 2, 0.5)):
        want = steepest(entries, y, {r["col_id"]: r["cb"] for r in part.collect()}, sweeps, share)
        got = {r["col_id"]: r["x"] for r in blocks.QUERIES[name](spark, "").collect()}
        assert got == pytest.approx(want, abs=1e-9) and len({round(v, 6) for v in got.values()}) > 8


def test_one_task_baselines_refuse_large_systems(f1):
    with pytest.raises(ValueError, match="one task"):
        baselines._whole(f1, None, 2)


def test_lengths_in_a_cube(spark):
    rays = geometry.parallel_rays(spark, 6, 9, 20.0)
    t = geometry.trace(rays, (8, 8))
    assert t.agg(F.min("val")).first()[0] > 0 and t.agg(F.max("val")).first()[0] <= math.sqrt(2) + 1e-9
    assert t.groupBy("row_id", "col_id").count().where("count > 1").count() == 0


def test_shadow_areas_in_space_add_up(spark):
    whole = geometry.shadow_3d(spark, 4, 60, 2.0, 66.0, 132.0, 0, 1, (8, 8, 8), (1, 1, 1)).orderBy("view").collect()
    parts = geometry.shadow_3d(spark, 4, 60, 2.0, 66.0, 132.0, 0, 2, (8, 8, 8), (1, 1, 1)).groupBy("view").agg(F.sum("p_s").alias("p_s")).orderBy("view").collect()
    assert [r["p_s"] for r in parts] == pytest.approx([r["p_s"] for r in whole])


def test_planted_truth_is_found(spark, tables):
    s = systems.assemble(systems.supplier(spark, tables))
    r = solver.solve(s, SolveSpec(epochs=4, refresh="epoch", strategy="packed"), measure_every=4)
    assert r.history.first()["gap_db"] > 3


def test_storage(f1, spark, tmp_path):
    store.write_blocks(f1.entries, str(tmp_path / "b"), 2)
    assert store.read_blocks(spark, str(tmp_path / "b")).exceptAll(f1.entries.select("cb", "rb", "row_id", "col_id", "val")).count() == 0
    for e in range(4):
        store.write_epoch(f1.x_zero(), str(tmp_path / "s"), e)
    assert sorted(p.name for p in (tmp_path / "s").glob("epoch=*")) == ["epoch=2", "epoch=3"]


def test_cone_rays_hit_a_perpendicular_detector(spark):
    """The source and the detector's centre lie on one line through the origin, and the detector is perpendicular to it."""
    rays = geometry.cone_rays(spark, 6, 5, 2.0).collect()
    for v in range(6):
        mine = [r for r in rays if r["view"] == v]
        src = np.array([mine[0]["src"][a] for a in "xyz"])
        dst = np.array([[r["dst"][a] for a in "xyz"] for r in mine])
        centre = dst.mean(0)
        assert np.linalg.norm(src) == pytest.approx(66) and np.linalg.norm(src - centre) == pytest.approx(132)
        assert np.allclose((dst - centre) @ src, 0, atol=1e-9) and np.allclose(np.cross(src, centre), 0, atol=1e-9)
        assert len(np.unique(dst.round(9), axis=0)) == 25


def test_noise_has_its_size(spark, tables):
    parts = systems.supplier(spark, tables)
    clean, noisy = systems.assemble(parts).y, systems.assemble(parts, noise_sd=3.0, seed=1).y
    row = clean.join(noisy.select("row_id", F.col("y").alias("z")), "row_id").agg(F.stddev(F.col("z") - F.col("y")).alias("sd"), F.avg(F.col("z") - F.col("y")).alias("mean"), F.count("*").alias("n")).first()
    assert row["sd"] == pytest.approx(3.0, rel=0.1) and abs(row["mean"]) < 4 * 3.0 / math.sqrt(row["n"])
