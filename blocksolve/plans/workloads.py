"""The experiments: one parameter at a time, on the scan and on systems over the given tables.

``race`` runs several settings on one system and stacks their histories: side by side, a task each, while the system fits a
task or while there are settings for all tasks (a larger system's entries then lie in files); together, with the rows dealt out to all tasks, while it fits these; else one after the other through the distributed solver. All draw the same blocks. The registered queries run all settings of their experiment to
its length on the small scan and on the tables; ``python -m blocksolve.plans.workloads W3 --scale paper`` takes the published scan.
Step bases are given as the mean relaxation b * s / m, which puts settings of different block counts on one scale (100 for single blocks
of 720 is 0.139). Groups of 100 of 720 row blocks become as large a share of the row blocks of other systems.
"""

from __future__ import annotations

import sys
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blocksolve.functions import geometry
from blocksolve.operators import baselines, measures, resident, solver
from blocksolve.operators import density as dens
from blocksolve.schema import LinearSystem, SolveSpec
from blocksolve.sources import systems
from blocksolve.sources.store import commit

QUERIES: dict = {}
SQL: dict[str, str] = {}
BLOCKS = SolveSpec(step_policy="area", refresh="column")
EFFECTIVE = 20  # effective epochs of most experiments


def query(name: str):
    def add(f):
        QUERIES[f"wl_{name}"] = f
        return f

    return add


def planted(parts: systems.Parts) -> LinearSystem:
    """The written system of ``parts``; its observations come from the written entries, which are made once."""
    s = systems.assemble(parts)
    s = replace(s, entries=commit(s.entries, "entries"))
    return replace(s, y=commit(systems.observe(s.entries, s.rows, s.x_true()), "y"), rows=commit(s.rows, "rows"), cols=commit(s.cols, "cols"))


def written(s: LinearSystem) -> LinearSystem:
    return replace(s, entries=commit(s.entries, "entries"), y=commit(s.y, "y"), rows=commit(s.rows, "rows"), cols=commit(s.cols, "cols"))


def shape_of(scale: str) -> tuple[int, int, int, float]:
    """Pixels a side, views, detector cells, radius."""
    return (64, 360, 187, 115.0) if scale == "paper" else (16, 36, 47, 29.0)


def scan(spark: SparkSession, scale: str = "small", subs: int = 2, parts: tuple[int, int] = (2, 2)) -> LinearSystem:
    """The planar scan; its density is the closed form of block shadows."""
    n, views, dets, radius = shape_of(scale)
    s = written(systems.assemble(systems.fan2d(spark, None, n, views, dets, radius, 1.0, subs, parts)))
    d = geometry.shadow_2d(spark, views, dets, radius, 1.0, subs, (n, n), parts)
    return replace(s, density=commit(dens.with_shares(d.select("cb", "rb", "view", "p_s")), "density"))


def basket(spark: SparkSession, d: str, m: int = 72, n: int = 4) -> LinearSystem:
    """Orders by parts; column blocks by part number."""
    entries, rows, cols = systems.basket(spark, d, m)
    return planted((entries, rows, cols.withColumn("cb", F.pmod("col_id", F.lit(n)).cast("int"))))


def moving(spark: SparkSession, d: str, segment: int = 91) -> LinearSystem:
    """Windows of days: the width is the view, runs of ``segment`` window starts its parts; column blocks are years."""
    entries, rows, cols = systems.moving(spark, d, quarter=segment)
    return planted((entries, rows, cols.withColumn("cb", F.floor(F.col("col_id") / 366).cast("int"))))


def terms(spark: SparkSession, d: str) -> LinearSystem:
    return planted(systems.terms(spark, d))


@dataclass(frozen=True)
class Field:
    """A system that settings race on. ``m``: row blocks that a column block has entries in (on the scan: all); ``share``: their part of all row blocks."""

    name: str
    system: LinearSystem
    m: int
    share: float = 1.0

    @classmethod
    def of(cls, name: str, s: LinearSystem) -> Field:
        m = s.rows.select("rb").distinct().count()
        if s.density is not None:
            return cls(name, s, m)
        s = replace(s, density=commit(solver.density_of(s), "density"))
        some = s.density.where("p_s > 0").agg(F.count("*") / F.countDistinct("cb")).first()[0]
        return cls(name, s, max(1, round(some)), some / m)

    def spec(self, mean: float, group: int = 1, row_fraction: float = 1.0, **how) -> SolveSpec:
        """The step base that gives single blocks or groups the mean relaxation ``mean``; row fractions count the blocks that have entries."""
        group = min(group, self.m)
        return replace(BLOCKS, step_base=mean * self.m / group, group_size=group, row_fraction=min(1.0, row_fraction * self.share), **how)

    def of_100(self) -> int:
        """Groups of 100 of 720, as a share of m."""
        return max(2, round(100 * self.m / 720))

    def groups(self) -> dict[int, tuple[int, float]]:
        """Published group size: group size here, mean relaxation."""
        return {1: (1, 0.139), 5: (5, 0.174), 100: (self.of_100(), 0.278)}


def length(effective: float, row_fraction: float, col_fraction: float = 1.0) -> int:
    return max(1, round(effective / row_fraction / col_fraction))


def run_all(system: LinearSystem, settings: dict[str, SolveSpec], checkpoints: tuple[int, ...] = ()) -> resident.Swept:
    density = solver.density_of(system)
    entries, tasks = system.entries.count(), system.entries.sparkSession.sparkContext.defaultParallelism
    if entries > resident.STORED and len(settings) >= tasks and resident.can_store(system):
        return resident.sweep_stored(system, density, settings, checkpoints)
    if entries <= resident.MOST and system.y.count() <= resident.MOST:
        return resident.sweep(system, density, settings, checkpoints)
    if resident.can_spread(system):
        return resident.spread(system, density, settings, checkpoints)
    history, x, refreshes = None, None, None
    for label, one in settings.items():
        r = solver.solve(system, one, label)
        parts = (r.history, r.x.select(F.lit(label).alias("run"), F.lit(one.epochs).alias("epoch"), "cb", "col_id", "x"), measures.refresh_counts(r.picks_log).select(F.lit(label).alias("run"), "cb", "rb", "refreshes"))
        history, x, refreshes = parts if history is None else (a.unionByName(b) for a, b in zip((history, x, refreshes), parts, strict=True))
    return resident.Swept(history, x, refreshes)


def race(*fields: tuple[Field, dict[str, SolveSpec]]) -> DataFrame:
    """system, run and the measures of every epoch; effective epochs count the blocks that have entries."""
    out = None
    for f, settings in fields:
        h = run_all(f.system, settings).history.withColumn("eff_epoch", F.col("eff_epoch") / f.share).select(F.lit(f.name).alias("system"), "*")
        out = h if out is None else out.unionByName(h)
    return out


def fields(spark: SparkSession, d: str, scale: str, *names: str) -> list[Field]:
    build = {"scan": lambda: scan(spark, scale), "moving": lambda: moving(spark, d), "terms": lambda: terms(spark, d), "basket": lambda: basket(spark, d)}
    return [Field.of(n, build[n]()) for n in names]


@query("w1_step_base")
def w1(spark, d, scale="small", effective=EFFECTIVE):
    means = {70: 0.097, 100: 0.139, 130: 0.18, 160: 0.222, 190: 0.264}
    return race(*((f, {f"b={b}": f.spec(mean, epochs=effective) for b, mean in means.items()}) for f in fields(spark, d, scale, "scan", "moving")))


@query("w2_row_fraction")
def w2(spark, d, scale="small", effective=EFFECTIVE):
    return race(*((f, {f"alpha={a}": f.spec(0.139, epochs=length(effective, a), row_fraction=a) for a in (1.0, 0.8, 0.5, 0.2)}) for f in fields(spark, d, scale, "scan", "moving", "terms")))


@query("w3_group_size")
def w3(spark, d, scale="small", effective=EFFECTIVE):
    return race(*((f, {f"s={k}": f.spec(mean, g, epochs=length(effective, 0.5), row_fraction=0.5) for k, (g, mean) in f.groups().items()}) for f in fields(spark, d, scale, "scan", "moving")))


def pictures(spark, scale, effective, sampler, fractions) -> tuple[LinearSystem, resident.Swept]:
    s = scan(spark, scale)
    f = Field.of("scan", s)
    return s, run_all(s, {f"s={k} alpha={a}": f.spec(mean, g, epochs=length(effective, a), row_fraction=a, sampler=sampler) for a in fractions for k, (g, mean) in f.groups().items()})


def regions(spark: SparkSession, scale: str) -> DataFrame:
    """col_id, region: cells near a border between column blocks, and the others."""
    n = shape_of(scale)[0]
    near = lambda c: F.abs(F.col(c) + 0.5 - n / 2) < n / 16
    return geometry.cells(spark, (n, n), (2, 2)).select("col_id", F.when(near("ix") | near("iy"), "margin").otherwise("rest").alias("region"))


def snr_table(spark: SparkSession, s: LinearSystem, x: DataFrame, scale: str) -> DataFrame:
    """run, region, snr_db of the last images; region "all" is the whole image."""
    last = x.join(x.groupBy("run").agg(F.max("epoch").alias("epoch")), ["run", "epoch"])
    both = last.join(s.x_true().select("col_id", F.col("x").alias("t")), "col_id").join(regions(spark, scale), "col_id")
    each = both.select("run", F.explode(F.array(F.lit("all"), F.col("region"))).alias("region"), (F.col("t") * F.col("t")).alias("a"), F.pow(F.col("t") - F.col("x"), F.lit(2)).alias("b"))
    return each.groupBy("run", "region").agg((10 * F.log10(F.sum("a") / F.sum("b"))).alias("snr_db"))


@query("w4_images")
def w4(spark, d, scale="small", effective=EFFECTIVE):
    """run, col_id, x: the six images."""
    x = pictures(spark, scale, effective, "density", (1.0, 0.5))[1].x
    return x.select("run", "col_id", "x")


@query("w4_snr")
def w4_snr(spark, d, scale="small", effective=EFFECTIVE):
    s, out = pictures(spark, scale, effective, "density", (1.0, 0.5))
    return snr_table(spark, s, out.x, scale)


SEGMENTS = {2: 365, 4: 91, 8: 30, 16: 7}  # days: years, quarters, months and weeks stand in for 2 to 16 parts


def part_races(spark, d, scale, effective, sampler) -> DataFrame:
    """Groups keep their number of row blocks (1, and 100 of 720) while the parts become more; published bases rise in
    proportion to the parts, which keeps the mean relaxation."""
    out, coarse = [], {}
    for subs, days in SEGMENTS.items():
        for name, s in (("scan", scan(spark, scale, subs)), ("moving", moving(spark, d, days))):
            f = Field.of(name, s)
            large = coarse.setdefault(name, f.of_100())
            out.append((f, {f"parts={subs} s={k} {sampler}": f.spec(mean, g, epochs=length(effective, 0.5), row_fraction=0.5, sampler=sampler) for k, g, mean in ((1, 1, 0.139), (100, large, 0.278))}))
    return race(*out)


@query("w5_detector_parts")
def w5(spark, d, scale="small", effective=EFFECTIVE):
    return part_races(spark, d, scale, effective, "density")


@query("w6_volume_parts")
def w6(spark, d, scale="small", effective=EFFECTIVE):
    out = []
    for p in (2, 4, 8, 16):
        for name, s in (("scan", scan(spark, scale, 2, (p, p))), ("basket", basket(spark, d, 72, p * p))):
            f = Field.of(name, s)
            out.append((f, {f"blocks={p * p}": f.spec(0.556 / p, f.of_100(), epochs=length(effective, 0.5), row_fraction=0.5)}))
    return race(*out)


@query("w7_column_fraction")
def w7(spark, d, scale="small", effective=EFFECTIVE):
    out = []
    for p, mean in ((4, 0.139), (8, 0.069)):
        for name, s in (("scan", scan(spark, scale, 2, (p, p))), ("basket", basket(spark, d, 72, p * p))):
            f = Field.of(name, s)
            out.append((f, {f"blocks={p * p} gamma={c}": f.spec(mean, f.of_100(), epochs=length(effective, 0.5, c), row_fraction=0.5, col_fraction=c) for c in (1.0, 0.75, 0.5, 0.25)}))
    return race(*out)


@query("w8_sampler_gain")
def w8(spark, d, scale="small", effective=50, repeats=10):
    """system, s, epoch, gain_db: mean SNR of ten runs with density sampling minus that of ten with uniform sampling."""
    out = None
    for f in fields(spark, d, scale, "scan", "moving", "terms"):
        sizes = f.groups() | {2: (2, 0.15)}
        runs = {f"{k} {sampler} {seed}": f.spec(mean, g, epochs=length(effective, 0.5), row_fraction=0.5, sampler=sampler, seed=seed) for k, (g, mean) in sizes.items() for sampler in ("density", "uniform") for seed in range(repeats)}
        h = run_all(f.system, runs).history
        for k in sizes:
            gain = measures.sampler_gain(*(h.where(F.col("run").startswith(f"{k} {sampler} ")) for sampler in ("density", "uniform")))
            gain = gain.select(F.lit(f.name).alias("system"), F.lit(k).alias("s"), "epoch", "gain_db")
            out = gain if out is None else out.unionByName(gain)
    return out


@query("w9_area_imbalance")
def w9(spark, d, scale="small"):
    out = [dens.imbalance(f.system.density).select(F.lit(f.name).alias("system"), "*") for f in fields(spark, d, scale, "scan", "moving")]
    return out[0].unionByName(out[1])


@query("w10_blend")
def w10(spark, d, scale="small", effective=EFFECTIVE):
    return race(*((f, {k: f.spec(0.278, f.of_100(), epochs=length(effective, 0.5), row_fraction=0.5, sampler=k) for k in ("density", "uniform", "blend")}) for f in fields(spark, d, scale, "scan", "moving", "terms")))


@query("w11_blend_images")
def w11(spark, d, scale="small", effective=EFFECTIVE):
    """run, region, snr_db with density sampling and with the blend: the error near the borders of blocks and elsewhere."""
    out = None
    for sampler in ("density", "blend"):
        s, swept = pictures(spark, scale, effective, sampler, (0.5,))
        t = snr_table(spark, s, swept.x, scale).select(F.lit(sampler).alias("sampler"), "*")
        out = t if out is None else out.unionByName(t)
    return out


@query("w12_blend_parts")
def w12(spark, d, scale="small", effective=EFFECTIVE):
    return part_races(spark, d, scale, effective, "blend")


@query("flat_stretches")
def flat(spark, d, scale="small", effective=50):
    """sampler, quarter, blocks, refreshes, flat_epochs: how often the projections of the blocks of least (1) to most (4) density
    were renewed, beside the epochs that the run spends on stretches without gain."""
    s = scan(spark, scale)
    f = Field.of("scan", s)
    out = run_all(s, {k: f.spec(0.278, f.of_100(), epochs=length(effective, 0.5), row_fraction=0.5, sampler=k) for k in ("density", "uniform", "blend")})
    flat = measures.plateaus(out.history, 0.1, 2).groupBy("run").agg(F.sum(F.col("last_epoch") - F.col("first_epoch") + 1).alias("flat_epochs"))
    quarter = s.density.where("p_s > 0").withColumn("quarter", F.ntile(4).over(Window.partitionBy("cb").orderBy("p", "rb")))
    grid = quarter.crossJoin(F.broadcast(out.history.select("run").distinct())).join(out.refreshes, ["run", "cb", "rb"], "left")
    per = grid.groupBy("run", "quarter").agg(F.count("*").alias("blocks"), F.avg(F.coalesce("refreshes", F.lit(0))).alias("refreshes"))
    return per.join(flat, "run", "left").select(F.col("run").alias("sampler"), "quarter", "blocks", "refreshes", F.coalesce("flat_epochs", F.lit(0)).alias("flat_epochs"))


CONES = {"small": (8, 24, 14), "middle": (16, 96, 26), "large": (32, 192, 52), "paper": (128, 720, 202)}  # voxels a side, views, detector cells a side


def cone(spark: SparkSession, scale: str) -> LinearSystem:
    """The published proportions: a cube of 32, radius 66, distance 132, detector of 101, measured in voxels."""
    side, views, dets = CONES[scale]
    f = side / 32
    s = written(systems.assemble(systems.cone3d(spark, None, side, views, dets, 101 * f / dets, 66 * f, 132 * f)))
    return s


@query("w13_cone")
def w13(spark, d, scale="small", checkpoints=(5, 50, 100, 200)):
    """eff_epoch, iz, snr_db at the checkpoints: the whole volume (iz null) and each slice. Undivided detector, 8 column blocks, groups of an eighth of the views."""
    s = cone(spark, scale)
    f, side = Field.of("cone", s), CONES[scale][0]
    at = tuple(2 * c for c in checkpoints)
    x = run_all(s, {"cone": f.spec(0.125, max(1, f.m // 8), epochs=at[-1], row_fraction=0.5)}, at).x
    place = geometry.cells(spark, (side, side, side), (2, 2, 2)).select("col_id", "iz")
    both = x.join(s.x_true().select("col_id", F.col("x").alias("t")), "col_id").join(place, "col_id")
    sums = both.rollup("epoch", "iz").agg(F.sum(F.col("t") * F.col("t")).alias("a"), F.sum(F.pow(F.col("t") - F.col("x"), F.lit(2))).alias("b")).where("epoch IS NOT NULL")
    return sums.select((F.col("epoch") / 2).alias("eff_epoch"), "iz", F.when(F.col("a") > 0, 10 * F.log10(F.col("a") / F.col("b"))).alias("snr_db"))


@query("w14_coin_floor")
def w14(spark, d, scale="small", effective=EFFECTIVE):
    return race(*((f, {k: f.spec(0.278, f.of_100(), epochs=length(effective, 0.5), row_fraction=0.5, sampler=k, floor=0.5 / f.m) for k in ("density", "coin", "floor")}) for f in fields(spark, d, scale, "moving", "terms")))


@query("w15_long_run")
def w15(spark, d, scale="small", epochs=1000):
    s, f = Field.of("supplier", planted(systems.supplier(spark, d))), Field.of("moving", moving(spark, d, 365))
    return race((s, {"long": SolveSpec(epochs=epochs, refresh="epoch")}), (f, {"long": f.spec(0.139, epochs=epochs, row_fraction=0.5)}))


@query("w16_costs")
def w16(spark, d, scale="small"):
    """system, subs, parts: multiply-adds, numbers moved and numbers held for several grids, one full epoch each."""
    out = None
    grids = [("scan", subs, p, lambda subs=subs, p=p: scan(spark, scale, subs, (p, p))) for subs, p in ((1, 2), (2, 2), (4, 2), (2, 4), (2, 8))]
    grids += [("basket", 1, p, lambda p=p: basket(spark, d, 72, p * p)) for p in (2, 4)] + [("moving", days, 1, lambda days=days: moving(spark, d, days)) for days in (91, 365)]
    for name, subs, p, build in grids:
        st = measures.block_stats(build().entries)
        row = st.agg((3 * F.sum("nnz")).alias("macs"), (2 * F.sum(F.col("n_rows") + F.col("n_cols"))).alias("moved"), F.max(F.col("n_rows") + F.col("n_cols")).alias("held"))
        row = row.select(F.lit(name).alias("system"), F.lit(subs).alias("subs"), F.lit(p).alias("parts"), "macs", "moved", "held")
        out = row if out is None else out.unionByName(row)
    return out


@query("asynchronous")
def asynchronous(spark, d, scale="small", effective=EFFECTIVE):
    """Workers that use the residual of some epochs ago, and epochs that leave column blocks out."""
    return race(*((f, {f"staleness={k}": f.spec(0.139, f.of_100(), epochs=length(effective, 0.5), row_fraction=0.5, staleness=k) for k in (0, 1, 2, 4)} | {f"gamma={c}": f.spec(0.139, f.of_100(), epochs=length(effective, 0.5, c), row_fraction=0.5, col_fraction=c) for c in (0.75, 0.5)}) for f in fields(spark, d, scale, "scan", "moving")))


@query("noisy")
def noisy(spark, d, scale="small", effective=EFFECTIVE):
    """A scan whose observations carry 5 % noise, with and without the ridge term, and with steps that adapt."""
    n, views, dets, radius = shape_of(scale)
    parts = systems.fan2d(spark, None, n, views, dets, radius, 1.0)
    clean = written(systems.assemble(parts))
    size = clean.y.agg(F.sqrt(F.avg(F.col("y") * F.col("y")))).first()[0]
    s = replace(written(systems.assemble((clean.entries.select("row_id", "col_id", "val"), clean.rows, clean.cols), noise_sd=0.05 * size, seed=3)), density=scan(spark, scale).density)
    f = Field.of("noisy scan", s)
    how = dict(epochs=length(effective, 0.5), row_fraction=0.5)
    return race((f, {f"ridge={k}": f.spec(0.278, f.of_100(), ridge=k, **how) for k in (0.0, 0.1, 1.0)} | {"adaptive": f.spec(0.278, f.of_100(), step_policy="adaptive", **how)}))


@query("w17_baselines")
def w17(spark, d, scale="small", epochs=1):
    """run, macs, gap_db after one sweep or epoch: multiply-adds are passes over the entries times their number.

    Two ways run at a time, in two lines; those that need one task are in the same line. As one plan, all their jobs would start
    together, and small ones would wait behind all large ones.
    """
    s = planted(systems.supplier(spark, d))
    zero, rbs, cbs = s.x_zero(), [0, 1, 2, 3], [0, 1]
    ways = {
        "sirt": lambda: baselines.row_action(s, zero, rbs, "sirt", 1.0, "sum"), "sart": lambda: baselines.row_action(s, zero, rbs, "sart", 1.0), "cav": lambda: baselines.row_action(s, zero, rbs, "cav", 1.0, "sum"),
        "bicav": lambda: baselines.row_action(s, zero, rbs, "bicav", 1.0), "columns": lambda: baselines.col_action(s, zero, cbs, "steepest"), "coordinates": lambda: baselines.coordinate_descent(s), "equations": lambda: baselines.kaczmarz(s),
        "averaged blocks": lambda: solver.epochs_lazily(s, SolveSpec(), 4, cbs).x,
    }
    passes, nnz, line, out = {"columns": 4, "averaged blocks": 3}, s.entries.count(), ["coordinates", "equations", "averaged blocks"], None

    def end(names: list[str]) -> dict[str, DataFrame]:
        return {k: commit(measures.gap_db(s.entries, commit(ways[k](), "x"), s.y), "gap") for k in names}

    with ThreadPoolExecutor(2) as pool:
        parts = [pool.submit(inheritable_thread_target(spark)(end), names) for names in (line, [k for k in ways if k not in line])]
        gaps = {k: g for p in parts for k, g in p.result().items()}
    for k in ways:
        g = gaps[k].select(F.lit(k).alias("run"), F.lit(passes.get(k, 2) * nnz).alias("macs"), "gap_db")
        out = g if out is None else out.unionByName(g)
    return out


@query("fbp")
def fbp(spark, d, scale="small"):
    """Filtered back-projection of a parallel scan: correlation with the truth and relative error."""
    n, views, dets = 16, 48, 47
    rays = geometry.parallel_rays(spark, views, dets, 29.0, 0.6)
    grid = geometry.phantom(geometry.cells(spark, (n, n), (2, 2)), (n, n))
    s = systems.assemble((geometry.trace(rays, (n, n)).select("row_id", "col_id", "val"), rays.select("row_id", "rb", "view", "sub"), grid.select("col_id", "cb", "x_true")))
    x = baselines.filtered_back_projection(rays, s.y, grid, (n, n), views, dets, 0.6)
    both = x.join(grid.select("col_id", "x_true"), "col_id")
    return both.agg(F.corr("x", "x_true").alias("corr"), (F.sqrt(F.sum(F.pow(F.col("x") - F.col("x_true"), F.lit(2)))) / F.sqrt(F.sum(F.col("x_true") * F.col("x_true")))).alias("error"))


def main(args: list[str]) -> None:
    spark = SparkSession.builder.master("local[*]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    options = dict(zip(args[1::2], args[2::2], strict=True))
    f = next(f for k, f in QUERIES.items() if k == f"wl_{args[0].lower()}" or k.startswith(f"wl_{args[0].lower()}_"))
    how = {"scale": options.get("--scale", "small")} | {k: int(options[f"--{k}"]) for k in ("effective", "epochs", "repeats") if f"--{k}" in options}
    f(spark, options.get("--tables", "/root/testdata/sf0.01"), **how).show(10000, False)


if __name__ == "__main__":
    main(sys.argv[1:])
