"""Queries beside their SQL on small tables made for a finding."""

import datetime as dt

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry
from blocksolve.operators import baselines
from blocksolve.plans import workloads
from blocksolve.sources import systems


def rows(df: pd.DataFrame) -> list[tuple]:
    return sorted(map(tuple, df[sorted(df.columns)].round(6).to_numpy().tolist()))


def compare(spark, name, folder, *tables):
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    got, want = entry.queries()[name](spark, str(folder)).toPandas(), con.execute(entry.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)
    return got


def events(folder, stamps):
    df = pd.DataFrame({"event_id": range(len(stamps)), "ts": pd.to_datetime(stamps), "user_id": 1, "event_type": "a", "value": 1.0, "props": "{}"})
    duckdb.sql("SELECT event_id, ts::TIMESTAMP AS ts, user_id, event_type, value, props FROM df").write_parquet(f"{folder}/events.parquet")


def test_interval_join_rounds_seconds_as_its_sql(spark, tmp_path):
    """A gap of 600.2 s over a whole second's middle, and one of 599.9 s that rounds to 601."""
    at = dt.datetime(2024, 1, 1, 10)
    events(tmp_path, [at + dt.timedelta(seconds=s) for s in (0.3, 600.5, 600.51, 600.49, 1200.9, 0.5, 1.5, 601.5, 602.5)])
    assert len(compare(spark, "op_interval_join", tmp_path, "events")) > 3


def test_hours_round_seconds_as_their_sql(spark, tmp_path):
    """An event 0.4 s before an hour belongs to the next one."""
    at = dt.datetime(2024, 1, 1)
    events(tmp_path, [at + dt.timedelta(seconds=s) for s in (0.2, 3599.2, 7199.5, 90 * 3600 - 0.4)])
    assert len(compare(spark, "sys_hours", tmp_path, "events")) > 0


READ_BY_RAYS = ["geo_fan_rays", "geo_ray_chord_sum", "geo_trace_2d", "geo_trace_block", "geo_parallel_rays", "geo_cone_rays", "geo_shadow_2d", "geo_shadow_imbalance", "geo_shadow_3d", "geo_trace_3d", "op_generated_source"]


@pytest.mark.parametrize("name", READ_BY_RAYS)
def test_scans_follow_the_rays_of_the_table(spark, tmp_path, name):
    """Customers are the rays: two more of them change the result; one without a balance is none."""
    made = []
    for more in ("", "one"):
        (tmp_path / f"t{more}").mkdir()
        c = pd.DataFrame({"c_custkey": range(40), "c_nationkey": [k % 5 + 3 for k in range(40)], "c_acctbal": [3000.0 + 40 * k for k in range(40)]})
        c.loc[7, "c_acctbal"] = None
        if more:
            c.loc[40], c.loc[41] = (40, 9, 4400.0), (41, 5, 4520.0)
        duckdb.sql("SELECT c_custkey::BIGINT AS c_custkey, c_nationkey::INT AS c_nationkey, c_acctbal FROM c").write_parquet(str(tmp_path / f"t{more}/customer.parquet"))
        if name in entry.oracle_sql():
            made.append(rows(compare(spark, name, tmp_path / f"t{more}", "customer")))
        else:
            made.append(rows(entry.queries()[name](spark, str(tmp_path / f"t{more}")).toPandas()))
    assert made[0] != made[1]


def whole_system(spark, rows_n=400, cols_n=40):
    """Rows of three entries over random columns."""
    import random

    from blocksolve.sources import systems

    r = random.Random(5)
    at = [(i, j, float(r.randint(1, 9))) for i in range(rows_n) for j in sorted(r.sample(range(cols_n), 3))]
    rws = spark.createDataFrame([(i, i % 4, i % 4, 0) for i in range(rows_n)], "row_id bigint, rb int, view int, sub int")
    cls = spark.createDataFrame([(j, j % 2, float(j)) for j in range(cols_n)], "col_id bigint, cb int, x_true double")
    return systems.assemble((spark.createDataFrame(at, "row_id bigint, col_id bigint, val double"), rws, cls)), at


def test_single_unknowns_and_equations_have_no_limit(spark):
    """No limit unless one is asked for; results against plain loops."""
    import inspect

    import numpy as np

    from blocksolve.operators import baselines

    assert inspect.signature(baselines._whole).parameters["most"].default is None
    s, at = whole_system(spark)
    a, y = np.zeros((400, 40)), np.zeros(400)
    for i, j, v in at:
        a[i, j] = v
    y[:] = a @ np.arange(40.0)
    x, r = np.zeros(40), y.copy()
    for j in range(40):
        d = a[:, j] @ r / (a[:, j] @ a[:, j])
        x[j] += d
        r -= d * a[:, j]
    z = np.zeros(40)
    for i in range(400):
        z += (y[i] - a[i] @ z) / (a[i] @ a[i]) * a[i]
    for got, want in ((baselines.coordinate_descent(s), x), (baselines.kaczmarz(s), z)):
        assert np.allclose([q["x"] for q in got.orderBy("col_id").collect()], want, atol=1e-9)


def test_equations_that_go_together_equal_a_loop():
    import numpy as np

    from blocksolve.operators import baselines

    rng = np.random.default_rng(1)
    col = np.concatenate([np.sort(rng.choice(2000, 4, False)) for _ in range(3000)]).astype(np.int32)
    val, at, y = rng.normal(size=12000), np.arange(3001) * 4, rng.normal(size=3000)
    norm = np.add.reduceat(val * val, at[:-1])
    for steps in (np.arange(3000), rng.choice(3000, 3000)):
        x, z = np.zeros(2000), np.zeros(2000)
        baselines._project(x, steps, at, col, val, y, norm, 0.7)
        for i in steps:
            c, a = col[at[i] : at[i + 1]], val[at[i] : at[i + 1]]
            z[c] += 0.7 * (y[i] - a @ z[c]) / norm[i] * a
        assert np.allclose(x, z, atol=1e-12)


def test_exact_solution_beyond_the_dense_limit(spark):
    from blocksolve.operators import baselines

    s, _ = whole_system(spark)
    got = baselines.exact_least_squares(s, dense=10)
    assert [q["x"] for q in got.orderBy("col_id").collect()] == pytest.approx(list(range(40)), abs=1e-6)


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_sweeps_over_blocks_do_not_double_their_plan(spark, tables):
    s = workloads.planted(systems.supplier(spark, tables))
    rows = [len(_plan(baselines.row_action(s, s.x_zero(), [0, 1, 2, 3][:k], "sart"))) for k in (2, 4)]
    cols = [len(_plan(baselines.col_action(s, s.x_zero(), [0, 1, 0, 1][:k], "steepest"))) for k in (2, 4)]
    assert rows[1] < 1.2 * rows[0] and cols[1] < 1.2 * cols[0]


def test_w17_leaves_no_work_for_one_plan(spark, tables):
    df = workloads.w17(spark, tables)
    assert "Join" not in _plan(df) and "Exchange" not in _plan(df)
    got = {r["run"]: r for r in df.collect()}
    assert list(got) == ["sirt", "sart", "cav", "bicav", "columns", "coordinates", "equations", "averaged blocks"]
    s = workloads.planted(systems.supplier(spark, tables))
    for way in ("sart", "bicav"):
        x = baselines.row_action(s, s.x_zero(), [0, 1, 2, 3], way, 1.0)
        assert abs(got[way]["gap_db"] - workloads.measures.gap_db(s.entries, x, s.y).first()[0]) < 1e-9
