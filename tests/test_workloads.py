"""What the experiments claim, on the small scan: one sweep of all settings, to the published length."""

import pytest

from blocksolve.operators import measures
from blocksolve.plans import workloads as w


@pytest.fixture(scope="module")
def runs(spark):
    s = w.scan(spark)
    f = w.Field.of("scan", s)
    half = dict(row_fraction=0.5, epochs=40)
    settings = {f"b={b}": f.spec(mean, epochs=20) for b, mean in ((70, 0.097), (100, 0.139), (130, 0.18), (160, 0.222))}
    settings |= {f"alpha={a}": f.spec(0.139, epochs=round(20 / a), row_fraction=a) for a in (0.8, 0.5, 0.2)}
    settings |= {f"s={k} alpha={a}": f.spec(mean, g, epochs=round(20 / a), row_fraction=a) for k, (g, mean) in f.groups().items() for a in (1.0, 0.5)}
    settings |= {f"{sampler} s={k}": f.spec(mean, g, sampler=sampler, **half) for sampler in ("uniform", "blend") for k, (g, mean) in f.groups().items()}
    settings |= {f"gamma={c}": f.spec(0.278, f.of_100(), row_fraction=0.5, epochs=round(40 / c), col_fraction=c) for c in (0.75, 0.5, 0.25)}
    swept = w.run_all(s, settings)
    h = swept.history.toPandas().sort_values("epoch")
    return s, swept, h


def at(h, run, effective, column="snr_db"):
    mine = h[h["run"] == run]
    return mine[mine["eff_epoch"] <= effective + 1e-9][column].iloc[-1]


def test_larger_steps_are_faster_up_to_the_fourth(runs):
    last = [at(runs[2], f"b={b}", 20) for b in (70, 100, 130, 160)]
    assert last == sorted(last) and len(set(last)) == 4


def test_smaller_row_fractions_are_faster_per_effective_epoch(runs):
    for effective in (5, 10, 17):
        got = [at(runs[2], r, effective) for r in ("b=100", "alpha=0.8", "alpha=0.5", "alpha=0.2")]
        assert got == sorted(got), (effective, got)


def test_larger_groups_are_faster_at_both_row_fractions(runs):
    for a in (1.0, 0.5):
        got = [at(runs[2], f"s={k} alpha={a}", 20) for k in (1, 5, 100)]
        assert got == sorted(got) and got[2] > got[0] + 5
    for k in (1, 5, 100):
        assert at(runs[2], f"s={k} alpha=0.5", 20) > at(runs[2], f"s={k} alpha=1.0", 20)


def test_density_sampling_is_ahead_early(runs):
    for k in (1, 5):
        assert at(runs[2], f"s={k} alpha=0.5", 3) > at(runs[2], f"uniform s={k}", 3)


def test_the_blend_removes_what_density_sampling_leaves(runs):
    """With groups of 100 the blend ends above density sampling, and its surrogate residual is the smaller one."""
    h = runs[2]
    assert at(h, "blend s=100", 20) > at(h, "s=100 alpha=0.5", 20)
    assert at(h, "blend s=100", 20, "surrogate_gap_db") > at(h, "s=100 alpha=0.5", 20, "surrogate_gap_db")
    assert abs(at(h, "blend s=100", 2) - at(h, "s=100 alpha=0.5", 2)) < 1.5


def test_leaving_out_few_column_blocks_changes_little(runs):
    full = at(runs[2], "s=100 alpha=0.5", 20)
    assert abs(at(runs[2], "gamma=0.75", 20) - full) < 5 and abs(at(runs[2], "gamma=0.5", 20) - full) < 7


def test_measures_of_a_real_history(runs):
    s, swept, h = runs
    some = swept.history.where("run IN ('b=70', 'b=160')")
    first = {r["run"]: r["epoch"] for r in measures.epochs_to(some, 12.0).collect()}
    for run, epoch in first.items():
        mine = h[h["run"] == run]
        assert epoch == mine[mine["gap_db"] >= 12.0]["epoch"].min()
    assert first["b=160"] < first["b=70"]
    assert {r["diverged"] for r in measures.diverged(some).collect()} == {False}
    picks = swept.refreshes.where("run = 'alpha=0.5'").agg({"refreshes": "sum"}).first()[0]
    assert picks == h[h["run"] == "alpha=0.5"]["picks"].max()


def test_rarely_drawn_blocks_are_those_of_low_density(runs):
    s, swept, _ = runs
    d = s.density.where("p_s > 0").join(swept.refreshes.where("run = 's=100 alpha=0.5'"), ["cb", "rb"], "left").fillna(0, ["refreshes"]).toPandas()
    low, high = d[d["p"] < d["p"].quantile(0.25)], d[d["p"] > d["p"].quantile(0.75)]
    assert low["refreshes"].mean() < 0.7 * high["refreshes"].mean()


def test_back_projection_resembles_the_truth(spark):
    row = w.QUERIES["wl_fbp"](spark, "").first()
    assert row["corr"] > 0.9 and row["error"] < 0.5
