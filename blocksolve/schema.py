"""The frames that modules exchange."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ENTRIES = "cb int, rb int, row_id bigint, col_id bigint, val double"
Y = "rb int, row_id bigint, y double"
X = "cb int, col_id bigint, x double"
ROWS = "row_id bigint, rb int, view int, sub int"
COLS = "col_id bigint, cb int, x_true double"
DENSITY = "cb int, rb int, view int, p_s double, p_t double, p double"
PICKS = "epoch int, cb int, rb int, pick_rank int, grp int"
Z = "cb int, rb int, row_id bigint, z double"
PACKED = "cb int, rb int, rows array<bigint>, cols array<bigint>, at array<int>, idx array<int>, val array<double>"


@dataclass(frozen=True)
class LinearSystem:
    """y = A x cut into blocks. ``rows`` and ``cols`` name the block of every row and column; ``entries`` are A's nonzeros."""

    entries: DataFrame
    y: DataFrame
    rows: DataFrame
    cols: DataFrame
    density: DataFrame | None = None

    def x_true(self) -> DataFrame:
        return self.cols.select("cb", "col_id", F.col("x_true").alias("x"))

    def x_zero(self) -> DataFrame:
        return self.cols.select("cb", "col_id", F.lit(0.0).alias("x"))


@dataclass(frozen=True)
class SolveSpec:
    """How to solve. ``refresh``: "column", "epoch" or how many column blocks share one residual. ``step_policy``: "area", "const" or "adaptive" (area, with a base that grows by 5 % after an epoch that raised the gap and halves after one that did not)."""

    epochs: int = 1
    row_fraction: float = 1.0
    col_fraction: float = 1.0
    group_size: int = 1
    step_base: float = 1.0
    step_policy: str = "const"
    sampler: str = "density"
    theta_step: float = 1 / 40
    coin_p: float = 0.5
    floor: float = 0.0
    refresh: str | int = "column"
    jacobi_damping: str | float = "auto"
    residual: str = "surrogate"
    last_group: str = "short"
    keep_empty: bool = False
    ridge: float = 0.0
    staleness: int = 0
    seed: int = 0
    tol: float = 0.0
    checkpoint_every: int = 1
    strategy: str = "relational"

    def __post_init__(self) -> None:
        if not (0 < self.row_fraction <= 1 and 0 < self.col_fraction <= 1):
            raise ValueError("row_fraction and col_fraction must be in (0, 1]")
        if self.group_size < 1 or self.step_base <= 0 or self.epochs < 0:
            raise ValueError("group_size must be 1 or more, step_base above 0, epochs 0 or more")
        if self.sampler not in ("density", "uniform", "blend", "coin", "floor"):
            raise ValueError(f"unknown sampler {self.sampler}")
        if self.step_policy not in ("const", "area", "adaptive"):
            raise ValueError(f"unknown step policy {self.step_policy}")
        if self.residual not in ("surrogate", "true") or self.last_group not in ("short", "full") or self.strategy not in ("relational", "packed"):
            raise ValueError("residual: surrogate or true; last_group: short or full; strategy: relational or packed")

    def theta(self, epoch: int) -> float:
        """0 in the first epoch, then ``theta_step`` more with each."""
        return min(1.0, (epoch - 1) * self.theta_step)


def validate(system: LinearSystem) -> None:
    """Raises ValueError unless blocks partition rows and columns and entries are finite and lie in known blocks."""
    bad = {
        "a row lies in several blocks": system.rows.groupBy("row_id").agg(F.count("*").alias("n")).where("n > 1"),
        "a column lies in several blocks": system.cols.groupBy("col_id").agg(F.count("*").alias("n")).where("n > 1"),
        "an entry is not finite": system.entries.where("isnan(val) OR abs(val) = double('inf') OR val IS NULL"),
        "an entry's row has no block": system.entries.join(system.rows, ["row_id", "rb"], "left_anti"),
        "an entry's column has no block": system.entries.join(system.cols, ["col_id", "cb"], "left_anti"),
    }
    for what, rows in bad.items():
        if not rows.isEmpty():
            raise ValueError(what)
    if system.entries.isEmpty():
        raise ValueError("the system has no entries")
