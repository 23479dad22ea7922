"""Queries on systems, densities, picks, block steps, epochs, baselines and measures, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksolve.operators import baselines as base
from blocksolve.operators import density as dens
from blocksolve.operators import measures, sampling, solver, step
from blocksolve.plans import sql
from blocksolve.schema import LinearSystem, SolveSpec
from blocksolve.sources import systems
from blocksolve.sources.store import commit

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, text: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return add


def supplier(spark: SparkSession, d: str) -> LinearSystem:
    """The system that most step queries use, its entries and observations written once."""
    s = systems.assemble(systems.supplier(spark, d))
    return replace(s, entries=commit(s.entries, "entries"), y=commit(s.y, "y"))


def rounded(df: DataFrame, *columns: str, digits: int = 4) -> DataFrame:
    """Sums of floating-point numbers depend on their order in the last digits."""
    return df.withColumns({c: F.round(c, digits) + 0.0 for c in columns})


# --- systems -----------------------------------------------------------------------------------

_SUM = "SELECT cb, rb, count(*) AS nnz, count(DISTINCT row_id) AS n_rows, count(DISTINCT col_id) AS n_cols, round(sum(val), 3) + 0.0 AS mass FROM ({}) GROUP BY 1, 2"
_BRAND = "(substr(p_brand, 7, 2)::INT - 1)"
_SLIDE = """SELECT (d // {per})::INT AS cb, (v * 100000 + s // {per})::INT AS rb, v * 1099511627776 + s AS row_id, d AS col_id, 1.0 AS val
  FROM (SELECT w.v, w.w, s.s FROM (VALUES {widths}) w(v, w), range(0, {n}) s(s) WHERE s.s + w.w <= {n}) q
  JOIN (SELECT p - (SELECT min(p) FROM pts) AS d FROM pts) x ON d BETWEEN q.s AND q.s + q.w - 1"""
_SYSTEM_SQL = {
    "basket": f"SELECT ({_BRAND} % 5)::INT AS cb, (l_orderkey % 8)::INT AS rb, l_orderkey AS row_id, l_partkey AS col_id, sum(l_quantity) AS val FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL",
    "supplier": "SELECT (s_nationkey % 2)::INT AS cb, (l_orderkey % 4)::INT AS rb, l_orderkey AS row_id, l_suppkey AS col_id, sum(l_quantity) AS val FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL",
    "shipday": "SELECT (datediff('day', DATE '1995-01-01', l_shipdate::DATE) // 365)::INT AS cb, (l_orderkey % 8)::INT AS rb, l_orderkey AS row_id, datediff('day', DATE '1995-01-01', l_shipdate::DATE) AS col_id, sum(l_quantity) AS val FROM lineitem GROUP BY ALL",
    "moving": "WITH pts AS (SELECT DISTINCT datediff('day', DATE '1995-01-01', l_shipdate::DATE) AS p FROM lineitem) "
    + _SLIDE.format(per=91, n="(SELECT max(p) - min(p) + 1 FROM pts)", widths="(0, 1), (1, 3), (2, 7), (3, 30)"),
    "hours": "WITH pts AS (SELECT DISTINCT (epoch(ts) - epoch(TIMESTAMP '2024-01-01'))::BIGINT // 3600 AS p FROM events) "
    + _SLIDE.format(per=24, n="(SELECT max(p) - min(p) + 1 FROM pts)", widths="(0, 1), (1, 3), (2, 6), (3, 24)"),
    "userday": """SELECT kind::INT AS cb, (datediff('day', DATE '1970-01-01', ts::DATE) % 6)::INT AS rb, user_id * 100000 + datediff('day', DATE '1970-01-01', ts::DATE) AS row_id, kind * 24 + hour(ts) AS col_id, sum(value) AS val
      FROM events JOIN (SELECT event_type, dense_rank() OVER (ORDER BY event_type) - 1 AS kind FROM (SELECT DISTINCT event_type FROM events)) USING (event_type)
      WHERE json_extract(props, '$.k') IS NOT NULL GROUP BY ALL HAVING sum(value) <> 0""",
    "terms": "WITH " + sql.TERMS + " SELECT * FROM entries",
    "vectors": "SELECT ((d - 1) * 8 // 64)::INT AS cb, (vec_id % 8)::INT AS rb, vec_id AS row_id, d - 1 AS col_id, embedding[d]::DOUBLE AS val FROM embeddings, range(1, 65) r(d) WHERE embedding[d] <> 0",
    "pages": """SELECT (tid % 3)::INT AS cb, (page_id % 4)::INT AS rb, page_id AS row_id, tid AS col_id, count(*)::DOUBLE AS val
      FROM (SELECT page_id, ('0x' || substr(md5(lower(t)), 1, 8))::BIGINT AS tid FROM (SELECT page_id, unnest(regexp_extract_all(html, '<([a-zA-Z][a-zA-Z0-9]*)', 1)) AS t FROM pages)) GROUP BY ALL""",
    "conversations": "SELECT (turn % 2)::INT AS cb, (conv_id % 4)::INT AS rb, conv_id AS row_id, turn * 10 + length(role) AS col_id, sum(length(text))::DOUBLE AS val FROM conversations GROUP BY ALL HAVING sum(length(text)) <> 0",
    "benchmark": """SELECT (ascii(c) % 2)::INT AS cb, (item_id % 4)::INT AS rb, item_id AS row_id, ascii(c) AS col_id, count(*)::DOUBLE AS val
      FROM (SELECT item_id, unnest(string_split(regexp_replace(lower(text), '[^a-z]', '', 'g'), '')) AS c FROM benchmark) WHERE c <> '' GROUP BY ALL""",
    "nation_grid": """SELECT s_nationkey AS cb, c_nationkey AS rb, l_orderkey AS row_id, l_suppkey AS col_id, sum(l_quantity) AS val FROM lineitem JOIN supplier ON l_suppkey = s_suppkey
      JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey GROUP BY ALL""",
}
for _name, _build in systems.RELATIONAL.items():

    def _system(spark: SparkSession, d: str, build=_build) -> DataFrame:
        e = systems.assemble(build(spark, d)).entries
        out = e.groupBy("cb", "rb").agg(F.count("*").alias("nnz"), F.countDistinct("row_id").alias("n_rows"), F.countDistinct("col_id").alias("n_cols"), F.sum("val").alias("mass"))
        return rounded(out, "mass", digits=3)

    query(f"sys_{_name}", _SUM.format(_SYSTEM_SQL[_name]))(_system)


@query("sys_observations", "WITH " + sql.SUPPLIER + " SELECT rb, row_id, round(y, 4) + 0.0 AS y FROM y")
def _(spark, d):
    return rounded(systems.assemble(systems.supplier(spark, d)).y, "y")


# --- density -----------------------------------------------------------------------------------

_TERM_DENSITY = "WITH " + sql.TERMS + " SELECT cb, rb, view, p_s, p_t, round(p, 9) AS p FROM density"


def term_density(spark: SparkSession, d: str, weight: str = "nnz") -> tuple[LinearSystem, DataFrame]:
    s = systems.assemble(systems.terms(spark, d))
    return s, dens.entry_density(s.entries, s.rows, weight)


@query("den_nnz", _TERM_DENSITY)
def _(spark, d):
    return rounded(term_density(spark, d)[1], "p", digits=9)


for _w, _expr in (("mass", "sum(val * val)"), ("sum", "sum(val)")):

    def _weighted(spark, d, w=_w):
        return rounded(term_density(spark, d, w)[1], "p", digits=9)

    query(f"den_{_w}", _TERM_DENSITY.replace("count(*)::DOUBLE AS p_s", f"{_expr} AS p_s"))(_weighted)


@query("den_view_total", "WITH " + sql.TERMS + " SELECT cb, view, count(*) AS row_blocks, round(sum(p), 9) AS p FROM density GROUP BY 1, 2")
def _(spark, d):
    return rounded(term_density(spark, d)[1].groupBy("cb", "view").agg(F.count("*").alias("row_blocks"), F.sum("p").alias("p")), "p", digits=9)


for _theta, _tag in ((0.0, "0"), (0.5, "half"), (1.0, "1")):

    def _blend(spark, d, theta=_theta):
        return rounded(dens.blended(term_density(spark, d)[1], theta).select("cb", "rb", "w"), "w", digits=9)

    query(f"den_blend_theta_{_tag}", "WITH " + sql.TERMS + f" SELECT cb, rb, round((p_s + {_theta} * (max(p_s) OVER (PARTITION BY cb, view) - p_s)) / p_t, 9) AS w FROM density")(_blend)


@query("den_floor", "WITH " + sql.TERMS + " SELECT cb, rb, round(greatest(p, 0.02), 9) AS w FROM density")
def _(spark, d):
    s, den = term_density(spark, d)
    return rounded(sampling.weights(den, s.rows, SolveSpec(sampler="floor", floor=0.02), 1).select("cb", "rb", "w"), "w", digits=9)


@query("den_imbalance", "WITH " + sql.TERMS + " SELECT cb, view, min(p_s) AS least, max(p_s) AS most, round(min(p_s) / max(p_s), 9) AS ratio FROM density GROUP BY 1, 2")
def _(spark, d):
    return rounded(dens.imbalance(term_density(spark, d)[1]), "ratio", digits=9)


def region_density(spark: SparkSession, d: str) -> DataFrame:
    """region and nation of the customer, order year, nonzeros: the grid's density at several resolutions."""
    t = lambda n: spark.read.parquet(f"{d}/{n}.parquet")
    line = t("lineitem").select("l_orderkey", "l_suppkey").distinct()
    place = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return line.join(place.select("o_orderkey", "r_name", "n_name", F.year("o_orderdate").alias("yr")), F.col("l_orderkey") == F.col("o_orderkey"))


_REGION = """(SELECT r_name, n_name, year(o_orderdate)::INT AS yr FROM (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem) JOIN orders ON l_orderkey = o_orderkey
 JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey)"""


@query("den_rollup", f"SELECT r_name, n_name, count(*) AS nnz FROM {_REGION} GROUP BY ROLLUP (r_name, n_name)")
def _(spark, d):
    return region_density(spark, d).rollup("r_name", "n_name").agg(F.count("*").alias("nnz"))


@query("den_cube", f"SELECT r_name, yr, count(*) AS nnz FROM {_REGION} GROUP BY CUBE (r_name, yr)")
def _(spark, d):
    return region_density(spark, d).cube("r_name", "yr").agg(F.count("*").alias("nnz"))


@query("den_grouping_sets", f"SELECT r_name, n_name, yr, count(*) AS nnz FROM {_REGION} GROUP BY GROUPING SETS ((r_name, yr), (n_name), ())")
def _(spark, d):
    region_density(spark, d).createOrReplaceTempView("block_regions")
    return spark.sql("SELECT r_name, n_name, yr, count(*) AS nnz FROM block_regions GROUP BY GROUPING SETS ((r_name, yr), (n_name), ())")


@query("den_pivot", "WITH " + sql.TERMS + " SELECT rb, " + ", ".join(f"coalesce(max(p_s) FILTER (WHERE cb = {c}), 0) AS cb{c}" for c in range(4)) + " FROM density GROUP BY rb")
def _(spark, d):
    p = term_density(spark, d)[1].groupBy("rb").pivot("cb", [0, 1, 2, 3]).agg(F.max("p_s"))
    return p.select("rb", *[F.coalesce(F.col(str(c)), F.lit(0.0)).alias(f"cb{c}") for c in range(4)])


# --- picks -------------------------------------------------------------------------------------

_PICK = "WITH " + sql.TERMS + " SELECT 3 AS epoch, cb, rb, pick_rank, grp FROM ({})"


def _picks(spark, d, **how) -> DataFrame:
    s, den = term_density(spark, d)
    return sampling.draw_row_blocks(den, s.rows, 20, SolveSpec(row_fraction=0.5, **how), 3).select("epoch", "cb", "rb", "pick_rank", "grp")


for _tag, _how, _weight, _take, _group in (
    ("uniform", {"sampler": "uniform"}, "1.0", 10, 1),
    ("density", {"sampler": "density"}, "p", 10, 1),
    ("blend", {"sampler": "blend"}, "(p_s + 0.05 * (max(p_s) OVER (PARTITION BY cb, view) - p_s)) / p_t", 10, 1),
    ("floor", {"sampler": "floor", "floor": 0.05}, "greatest(p, 0.05)", 10, 1),
    ("groups_short", {"group_size": 4}, "p", 10, 4),
    ("groups_full", {"group_size": 4, "last_group": "full"}, "p", 12, 4),
):
    _text = _PICK.format(sql.picks(3, _take, _weight, _group).replace("FROM density", "FROM (SELECT *, p AS p0 FROM density)"))
    if "OVER (PARTITION BY cb, view)" in _weight:
        _text = _PICK.format(sql.picks(3, _take, "w", _group).replace("FROM density", f"FROM (SELECT *, {_weight} AS w FROM density)"))
    query(f"pick_{_tag}", _text)(lambda spark, d, how=_how: _picks(spark, d, **how))

_coin = "density" if sampling.uniform_of(0, 3, "coin") < 0.5 else "uniform"
query("pick_coin", SQL[f"pick_{_coin}"])(lambda spark, d: _picks(spark, d, sampler="coin"))


@query("pick_cols_gamma", f"SELECT e.e::INT AS epoch, cb FROM range(1, 9) e(e), LATERAL (SELECT cb::INT AS cb FROM range(0, 25) c(cb) ORDER BY {sql.uniform(0, 'e.e', chr(39) + 'col' + chr(39), 'cb')} LIMIT 13)")
def _(spark, d):
    rows = [(e, cb) for e in range(1, 9) for cb in sampling.draw_col_blocks(list(range(25)), SolveSpec(col_fraction=0.5), e)]
    return spark.createDataFrame(rows, "epoch int, cb int")


@query("pick_coverage", "WITH " + sql.TERMS + ", k AS (" + " UNION ALL ".join(f"SELECT cb, rb FROM ({sql.picks(e, 10)})" for e in range(1, 6)) + ") SELECT cb, rb, count(*) AS refreshes FROM k GROUP BY 1, 2")
def _(spark, d):
    s, den = term_density(spark, d)
    den, rows, log = commit(den, "density"), commit(s.rows, "rows"), None
    for e in range(1, 6):
        p = sampling.draw_row_blocks(den, rows, 20, SolveSpec(row_fraction=0.5), e)
        log = p if log is None else log.unionByName(p)
    return measures.refresh_counts(log)


# --- block steps on the supplier system -----------------------------------------------------------

ALL = "SELECT cb, rb, view, (row_number() OVER (PARTITION BY cb ORDER BY rb) - 1)::INT AS grp, p_s, p_t FROM density WHERE cb IN ({})"
PAIRS = "SELECT cb, rb, view, ((row_number() OVER (PARTITION BY cb ORDER BY rb) - 1) // 2)::INT AS grp, p_s, p_t FROM density WHERE cb IN ({})"


def one_round(spark: SparkSession, d: str, group: int = 1, ridge: float = 0.0) -> dict[str, DataFrame]:
    """All parts of a round over all blocks from x = 0, with steps halved as two column blocks share the residual."""
    s = supplier(spark, d)
    den = dens.entry_density(s.entries, s.rows)
    from pyspark.sql import Window

    grp = F.floor((F.row_number().over(Window.partitionBy("cb").orderBy("rb")) - 1) / group).cast("int")
    picks = den.withColumn("grp", grp)
    spec = SolveSpec(step_base=1.0, group_size=group, ridge=ridge)
    beta = sampling.relaxation(picks, spec, 0.5)
    r = s.y.select("rb", "row_id", F.col("y").alias("r"))
    active = step.activate(s.entries, picks)
    xg = step.with_x(step.back_project(active, r), s.x_zero(), ridge)
    f = step.forward_pair(active, xg)
    mu = step.step_length(xg, f, beta, ridge)
    return {"s": s, "picks": picks, "r": r, "active": active, "xg": xg, "f": f, "mu": mu, "visits": sampling.visits(picks)}


_ONE = [(ALL.format("0, 1"), 0.5)]


@query("step_gradient", sql.epochs(_ONE, "SELECT cb, grp, col_id, round(g, 2) + 0.0 AS g FROM g1"))
def _(spark, d):
    return rounded(one_round(spark, d)["xg"].select("cb", "grp", "col_id", "g"), "g", digits=2)


@query("step_length", sql.epochs(_ONE, "SELECT cb, grp, beta, round(mu, 12) AS mu FROM m1"))
def _(spark, d):
    return rounded(one_round(spark, d)["mu"].select("cb", "grp", "beta", "mu"), "mu", digits=12)


@query("step_proposal", sql.epochs(_ONE, "SELECT cb, grp, col_id, round(x + mu * g, 4) + 0.0 AS x FROM g1 JOIN m1 USING (cb, grp)"))
def _(spark, d):
    p = one_round(spark, d)
    return rounded(step.propose(p["xg"], p["mu"]), "x")


@query("step_residual_update", sql.epochs([(ALL.format("0"), 1.0)], "SELECT rb, r.row_id, round(r - coalesce(d, 0), 3) + 0.0 AS r FROM r1 r LEFT JOIN (SELECT row_id, sum(mu * ag) AS d FROM f1 JOIN m1 USING (cb, grp) GROUP BY 1) q ON r.row_id = q.row_id"))
def _(spark, d):
    p = one_round(spark, d)
    first = lambda df: df.where("cb = 0")
    mu = first(p["mu"]).withColumn("mu", F.col("mu") * 2)
    return rounded(step.residual_step(p["r"], first(p["f"]), mu), "r", digits=3)


@query("step_forward", sql.epochs(_ONE, "SELECT cb, rb, row_id, round(ax + mu * ag, 3) + 0.0 AS z FROM f1 JOIN m1 USING (cb, grp)"))
def _(spark, d):
    p = one_round(spark, d)
    return rounded(step.forward_project(p["active"], step.propose(p["xg"], p["mu"])), "z", digits=3)


@query("step_block_step", sql.epochs([("SELECT cb, rb, view, 0 AS grp, p_s, p_t FROM density WHERE cb = 1 AND rb = 2", 1.0)], "SELECT cb, col_id, round(x, 4) + 0.0 AS x FROM x1"))
def _(spark, d):
    s = supplier(spark, d)
    picks = dens.entry_density(s.entries, s.rows).where("cb = 1 AND rb = 2").withColumn("grp", F.lit(0))
    return rounded(solver.round_of(s, solver.start(s), picks, SolveSpec(step_base=1.0), 1).x, "x")


@query("step_grouped_step", sql.epochs([(PAIRS.format("0, 1"), 0.5)], "SELECT cb, grp, round(num, 0) + 0.0 AS num, round(mu, 12) AS mu FROM m1"))
def _(spark, d):
    return rounded(rounded(one_round(spark, d, 2)["mu"].select("cb", "grp", "num", "mu"), "mu", digits=12), "num", digits=0)


@query("step_zero_gradient", "WITH " + sql.SUPPLIER + " SELECT DISTINCT cb, rb AS grp, 0.0::DOUBLE AS mu FROM density")
def _(spark, d):
    p = one_round(spark, d)
    none = p["xg"].withColumn("g", F.lit(0.0))
    f = step.forward_pair(p["active"], none)
    return step.step_length(none, f, sampling.relaxation(p["picks"], SolveSpec())).select("cb", "grp", "mu")


@query("step_ridge", sql.epochs(_ONE, "SELECT cb, col_id, round(x, 4) + 0.0 AS x FROM x1", ridge=50.0))
def _(spark, d):
    p = one_round(spark, d, ridge=50.0)
    return rounded(step.average(p["s"].x_zero(), p["xg"], p["mu"], p["visits"]), "x")


@query("step_objective", "WITH " + sql.SUPPLIER + " SELECT round(sum(y * y), 0) AS objective FROM y WHERE rb < 2")
def _(spark, d):
    s = supplier(spark, d)
    return rounded(step.objective(s.entries, s.x_zero(), s.y.where("rb < 2")), "objective", digits=0)


# --- epochs ------------------------------------------------------------------------------------

_COLUMN = [(ALL.format(c), 1.0) for c in (0, 1)]
_TAKE_X = "SELECT cb, col_id, round(x, 3) + 0.0 AS x FROM x{}"


def _draws(epoch: int, take: int, cb: int | None, group: int = 1, weight: str = "p") -> str:
    where = "true" if cb is None else f"cb = {cb}"
    return sql.picks(epoch, take, weight, group, where=where)


def _epochs(name: str, spec: SolveSpec, rounds: list, last: str | None = None, **how) -> None:
    def run(spark: SparkSession, d: str) -> DataFrame:
        return rounded(solver.epochs_lazily(supplier(spark, d), spec, 4, [0, 1]).x, "x", digits=3)

    query(f"abd_{name}", sql.epochs(rounds, last or _TAKE_X.format(len(rounds)), **how))(run)


_epochs("one_epoch_column", SolveSpec(), _COLUMN)
_epochs("one_epoch_epoch", SolveSpec(refresh="epoch"), _ONE)
_epochs("two_epochs", SolveSpec(epochs=2), _COLUMN * 2)
_epochs("two_epochs_epoch", SolveSpec(epochs=2, refresh="epoch"), _ONE * 2)
_epochs("sampled_epoch", SolveSpec(epochs=2, row_fraction=0.5), [(_draws(e, 2, c), 1.0) for e in (1, 2) for c in (0, 1)])
_epochs("uniform_epoch", SolveSpec(epochs=2, row_fraction=0.5, sampler="uniform"), [(_draws(e, 2, c, weight="1.0"), 1.0) for e in (1, 2) for c in (0, 1)])
_epochs("grouped_epoch", SolveSpec(row_fraction=1.0, group_size=2), [(_draws(1, 4, c, 2), 1.0) for c in (0, 1)])
_epochs("area_steps", SolveSpec(row_fraction=0.5, step_policy="area", step_base=4.0), [(_draws(1, 2, c), 4.0) for c in (0, 1)], beta="{base} * sum(p_s) / max(p_t)")


def _blended_draws(epoch: int, cb: int) -> str:
    """All row blocks are one view here; the blend has moved by 0.4 an epoch, from 0 in the first."""
    return sql.picks(epoch, 2, "w", where=f"cb = {cb}").replace("FROM density", f"FROM (SELECT *, (p_s + {0.4 * (epoch - 1)!r} * (max(p_s) OVER (PARTITION BY cb) - p_s)) / p_t AS w FROM density)")


@query("abd_blend_epoch", sql.epochs([(_blended_draws(e, c), 1.0) for e in (1, 2, 3) for c in (0, 1)], _TAKE_X.format(6)))
def _(spark, d):
    s = supplier(spark, d)
    s = replace(s, rows=s.rows.withColumn("view", F.lit(0)))
    return rounded(solver.epochs_lazily(s, SolveSpec(epochs=3, row_fraction=0.5, sampler="blend", theta_step=0.4), 4, [0, 1]).x, "x", digits=3)


_epochs("true_residual", SolveSpec(residual="true", refresh="epoch", epochs=2), _ONE * 2, residual="true")
_epochs("ridge_epoch", SolveSpec(ridge=50.0), _COLUMN, ridge=50.0)
_gamma = [sampling.draw_col_blocks([0, 1], SolveSpec(col_fraction=0.5), e)[0] for e in (1, 2)]
_epochs("gamma_half", SolveSpec(epochs=2, col_fraction=0.5), [(ALL.format(c), 1.0) for c in _gamma])


@query("abd_packed_epoch", SQL["abd_two_epochs"])
def _(spark, d):
    return rounded(solver.epochs_lazily(supplier(spark, d), SolveSpec(epochs=2, strategy="packed"), 4, [0, 1]).x, "x", digits=3)


@query("abd_packed_grouped", SQL["abd_grouped_epoch"])
def _(spark, d):
    return rounded(solver.epochs_lazily(supplier(spark, d), SolveSpec(group_size=2, strategy="packed"), 4, [0, 1]).x, "x", digits=3)


@query("abd_touched_refresh", sql.epochs([(_draws(1, 2, None), 0.5)], "SELECT rb, y.row_id, round(y - coalesce(z, 0), 2) + 0.0 AS r FROM y LEFT JOIN (SELECT row_id, sum(z) AS z FROM z1 GROUP BY 1) q ON y.row_id = q.row_id"))
def _(spark, d):
    s = supplier(spark, d)
    picks = sampling.draw_row_blocks(dens.entry_density(s.entries, s.rows), s.rows, 4, SolveSpec(row_fraction=0.5), 1)
    begin = solver.start(s)
    new = solver.round_of(s, begin, picks, SolveSpec(row_fraction=0.5), 2)
    return rounded(step.surrogate_residual_touched(begin.r, begin.z, new.z, picks), "r", digits=2)


@query("abd_surrogate_after_epoch", sql.epochs(_COLUMN, "SELECT rb, y.row_id, round(y - coalesce(z, 0), 2) + 0.0 AS r FROM y LEFT JOIN (SELECT row_id, sum(z) AS z FROM z2 GROUP BY 1) q ON y.row_id = q.row_id"))
def _(spark, d):
    return rounded(solver.epochs_lazily(supplier(spark, d), SolveSpec(), 4, [0, 1]).r, "r", digits=2)


# --- baselines: one sweep -------------------------------------------------------------------------

_W = {
    "none": "SELECT rb, row_id, 1.0 AS w FROM entries GROUP BY 1, 2",
    "row_norm": "SELECT rb, row_id, 1 / sum(val * val) AS w FROM entries GROUP BY 1, 2",
    "sart": "SELECT rb, row_id, 1 / sum(val) AS w FROM entries GROUP BY 1, 2",
    "sirt": "SELECT rb, row_id, 1 / sum(val) AS w FROM entries GROUP BY 1, 2",
    "cav": "SELECT rb, row_id, 1 / sum(s * val * val) AS w FROM entries JOIN (SELECT col_id, count(*) AS s FROM entries GROUP BY 1) USING (col_id) GROUP BY 1, 2",
    "bicav": "SELECT rb, row_id, 1 / sum(s * val * val) AS w FROM entries JOIN (SELECT rb, col_id, count(*) AS s FROM entries GROUP BY 1, 2) USING (rb, col_id) GROUP BY 1, 2",
}
_C = {"sirt": "SELECT rb, col_id, 1 / sum(val) OVER (PARTITION BY col_id) AS c FROM (SELECT rb, col_id, sum(val) AS val FROM entries GROUP BY 1, 2)", "sart": "SELECT rb, col_id, 1 / sum(val) AS c FROM entries GROUP BY 1, 2"}


def row_sql(weight: str, omega: float, mode: str) -> str:
    ctes = [f"w AS MATERIALIZED ({_W[weight]})", f"c AS MATERIALIZED ({_C.get(weight, 'SELECT DISTINCT rb, col_id, 1.0 AS c FROM entries')})", "x0 AS MATERIALIZED (SELECT cb, col_id, 0.0::DOUBLE AS x FROM cols)"]
    sweeps = ["rb = 0", "rb = 1", "rb = 2", "rb = 3"] if mode == "sequential" else ["true"]
    for t, where in enumerate(sweeps, 1):
        ctes.append(f"""x{t} AS MATERIALIZED (WITH r AS (SELECT y.rb, y.row_id, (y - coalesce(a, 0)) * w AS r FROM y LEFT JOIN (SELECT row_id, sum(val * x) AS a FROM entries JOIN x{t - 1} USING (col_id) GROUP BY 1) q ON q.row_id = y.row_id
          JOIN w ON w.row_id = y.row_id WHERE {where.replace('rb', 'y.rb')}),
          g AS (SELECT col_id, sum(g * c) * {omega} AS move FROM (SELECT e.rb, e.col_id, sum(val * r) AS g FROM entries e JOIN r USING (row_id) GROUP BY 1, 2) JOIN c USING (rb, col_id) GROUP BY 1)
          SELECT cb, x.col_id, x + coalesce(move, 0) AS x FROM x{t - 1} x LEFT JOIN g ON g.col_id = x.col_id)""")
    return "WITH " + sql.SUPPLIER + ",\n" + ",\n".join(ctes) + f"\nSELECT cb, col_id, round(x, 3) + 0.0 AS x FROM x{len(sweeps)}"


for _tag, _weight, _omega, _mode in (
    ("row_action_seq", "row_norm", 0.01, "sequential"), ("row_action_sum", "row_norm", 0.01, "sum"), ("row_action_mean", "row_norm", 0.04, "mean"),
    ("row_action_plain", "none", 1e-6, "sum"), ("kaczmarz_block", "row_norm", 0.02, "sequential"), ("sart", "sart", 1.0, "sequential"), ("sirt", "sirt", 1.0, "sum"),
    ("sirt_block", "sirt", 1.0, "sequential"), ("cav", "cav", 1.0, "sum"), ("bicav", "bicav", 1.0, "sequential"),
):

    def _row(spark, d, weight=_weight, omega=_omega, mode=_mode):
        s = supplier(spark, d)
        return rounded(base.row_action(s, s.x_zero(), [0, 1, 2, 3], weight, omega, mode), "x", digits=3)

    query(f"base_{_tag}", row_sql(_weight, _omega / (4 if _mode == "mean" else 1), _mode))(_row)


def col_sql(weight: str, omega: float, mode: str) -> str:
    scale = "1 / n.n" if weight == "exact1d" else "mu"
    ctes = ["n AS MATERIALIZED (SELECT col_id, sum(val * val) AS n FROM entries GROUP BY 1)", "x0 AS MATERIALIZED (SELECT cb, col_id, 0.0::DOUBLE AS x FROM cols)"]
    sweeps = ["cb = 0", "cb = 1"] if mode == "sequential" else ["true"]
    for t, where in enumerate(sweeps, 1):
        ctes.append(f"""x{t} AS MATERIALIZED (WITH r AS (SELECT y.row_id, y - coalesce(a, 0) AS r FROM y LEFT JOIN (SELECT row_id, sum(val * x) AS a FROM entries JOIN x{t - 1} USING (col_id) GROUP BY 1) q ON q.row_id = y.row_id),
          g AS (SELECT cb, col_id, sum(val * r) AS g FROM entries JOIN r USING (row_id) WHERE {where} GROUP BY 1, 2),
          a AS (SELECT cb, sum(ag * ag) AS den FROM (SELECT e.cb, row_id, sum(val * g) AS ag FROM entries e JOIN g USING (col_id) GROUP BY 1, 2) GROUP BY 1),
          m AS (SELECT g.cb, sum(g * g) / min(den) AS mu FROM g JOIN a USING (cb) GROUP BY 1)
          SELECT x.cb, x.col_id, x + coalesce({omega} * {scale} * g, 0) AS x FROM x{t - 1} x LEFT JOIN g ON g.col_id = x.col_id LEFT JOIN n ON n.col_id = x.col_id LEFT JOIN m ON m.cb = x.cb)""")
    return "WITH " + sql.SUPPLIER + ",\n" + ",\n".join(ctes) + f"\nSELECT cb, col_id, round(x, 3) + 0.0 AS x FROM x{len(sweeps)}"


for _tag, _weight, _omega, _mode in (
    ("col_action_seq", "exact1d", 0.05, "sequential"), ("col_action_sum", "exact1d", 0.05, "sum"), ("col_action_mean", "exact1d", 0.1, "mean"), ("block_icd", "steepest", 1.0, "sequential"),
):

    def _col(spark, d, weight=_weight, omega=_omega, mode=_mode):
        s = supplier(spark, d)
        return rounded(base.col_action(s, s.x_zero(), [0, 1], weight, omega, mode), "x", digits=3)

    query(f"base_{_tag}", col_sql(_weight, _omega / (2 if _mode == "mean" else 1), _mode))(_col)


@query("base_true_residual", SQL["abd_true_residual"])
def _(spark, d):
    return QUERIES["abd_true_residual"](spark, d)


def volume(spark: SparkSession) -> tuple[LinearSystem, DataFrame]:
    """A small scan of a cube, and its cells."""
    from blocksolve.functions import geometry

    s = systems.assemble(systems.cone3d(spark, None, 4, 8, 8, 2.0, 12.0, 24.0))
    return replace(s, entries=commit(s.entries, "entries"), y=commit(s.y, "y")), geometry.cells(spark, (4, 4, 4), (2, 2, 2))


@query("base_slice_tiles")
def _(spark, d):
    """Column blocks of square tiles, slice by slice."""
    s, cells = volume(spark)
    return base.block_descent(base.recut(s, base.tile_blocks(cells, 4)))


@query("base_axial_lines")
def _(spark, d):
    """Column blocks of lines along the axis."""
    s, cells = volume(spark)
    return base.block_descent(base.recut(s, base.axial_blocks(cells, 2)))


@query("base_axial_topchange")
def _(spark, d):
    """Lines along the axis; the second sweep visits the half that the first moved most."""
    s, cells = volume(spark)
    return base.block_descent(base.recut(s, base.axial_blocks(cells, 2)), 2, 0.5)


@query("base_icd_cycle")
def _(spark, d):
    return base.coordinate_descent(supplier(spark, d), 2)


@query("base_icd_topchange")
def _(spark, d):
    return base.coordinate_descent(supplier(spark, d), 4, "last_change")


@query("base_kaczmarz")
def _(spark, d):
    return base.kaczmarz(supplier(spark, d), 2)


@query("base_rand_row")
def _(spark, d):
    return base.kaczmarz(supplier(spark, d), 2, randomized=True)


@query("base_normal_matrix", "WITH " + sql.SUPPLIER + " SELECT a.col_id AS col_a, b.col_id AS col_b, round(sum(a.val * b.val), 2) + 0.0 AS v FROM entries a JOIN entries b USING (row_id) WHERE a.col_id <= b.col_id GROUP BY 1, 2")
def _(spark, d):
    return rounded(base.normal_matrix(supplier(spark, d).entries), "v", digits=2)


@query("base_exact_lstsq", "SELECT (s_nationkey % 2)::INT AS cb, s_suppkey AS col_id, round(s_acctbal, 2) + 0.0 AS x FROM supplier")
def _(spark, d):
    return rounded(base.exact_least_squares(supplier(spark, d)), "x", digits=2)


# --- measures ----------------------------------------------------------------------------------

_AFTER = _COLUMN
_RES = "(SELECT y.row_id, y, y - coalesce(a, 0) AS r FROM y LEFT JOIN (SELECT row_id, sum(val * x) AS a FROM entries JOIN x2 USING (cb, col_id) GROUP BY 1) q ON q.row_id = y.row_id)"


def _after(spark, d):
    s = supplier(spark, d)
    return s, solver.epochs_lazily(s, SolveSpec(), 4, [0, 1])


@query("meas_snr", sql.epochs(_AFTER, "SELECT round(10 * log10(sum(x_true * x_true) / sum((x_true - x) * (x_true - x))), 6) AS snr_db FROM x2 JOIN cols USING (cb, col_id)"))
def _(spark, d):
    s, st = _after(spark, d)
    return rounded(measures.snr_db(s.x_true(), st.x), "snr_db", digits=6)


@query("meas_gap", sql.epochs(_AFTER, f"SELECT round(10 * log10(sum(y * y) / sum(r * r)), 6) AS gap_db FROM {_RES}"))
def _(spark, d):
    s, st = _after(spark, d)
    return rounded(measures.gap_db(s.entries, st.x, s.y), "gap_db", digits=6)


@query("meas_surrogate_gap", sql.epochs(_AFTER, "SELECT round(10 * log10(sum(y * y) / sum((y - coalesce(z, 0)) * (y - coalesce(z, 0)))), 6) AS gap_db FROM y LEFT JOIN (SELECT row_id, sum(z) AS z FROM z2 GROUP BY 1) q ON y.row_id = q.row_id"))
def _(spark, d):
    s, st = _after(spark, d)
    return rounded(measures.surrogate_gap_db(s.y, st.r), "gap_db", digits=6)


@query("meas_snr_region", sql.epochs(_AFTER, "SELECT (col_id % 3)::INT AS region, round(10 * log10(sum(x_true * x_true) / sum((x_true - x) * (x_true - x))), 6) AS snr_db FROM x2 JOIN cols USING (cb, col_id) GROUP BY 1"))
def _(spark, d):
    s, st = _after(spark, d)
    regions = s.cols.select("col_id", F.pmod("col_id", F.lit(3)).cast("int").alias("region"))
    return rounded(measures.snr_by_region(s.x_true(), st.x, regions), "snr_db", digits=6)


_PICKED = "k AS (" + " UNION ALL ".join(f"SELECT {e} AS epoch, cb, rb FROM ({sql.picks(e, 2)})" for e in (1, 2, 3)) + "), st AS (SELECT cb, rb, count(*) AS nnz, count(DISTINCT row_id) AS n_rows, count(DISTINCT col_id) AS n_cols FROM entries GROUP BY 1, 2)"


def _log(spark, d):
    s = supplier(spark, d)
    den, out = dens.entry_density(s.entries, s.rows), None
    for e in (1, 2, 3):
        p = sampling.draw_row_blocks(den, s.rows, 4, SolveSpec(row_fraction=0.5), e)
        out = p if out is None else out.unionByName(p)
    return commit(out, "picks"), measures.block_stats(s.entries)


@query("meas_macs", f"WITH {sql.SUPPLIER}, {_PICKED} SELECT epoch, (3 * sum(nnz))::BIGINT AS macs FROM k JOIN st USING (cb, rb) GROUP BY 1")
def _(spark, d):
    return measures.macs(*_log(spark, d))


@query("meas_transfer", f"WITH {sql.SUPPLIER}, {_PICKED} SELECT epoch, (2 * sum(n_rows + n_cols))::BIGINT AS numbers FROM k JOIN st USING (cb, rb) GROUP BY 1")
def _(spark, d):
    return measures.transfer(*_log(spark, d))


@query("meas_memory", f"WITH {sql.SUPPLIER}, {_PICKED} SELECT epoch, max(n_rows + n_cols)::BIGINT AS local_numbers FROM k JOIN st USING (cb, rb) GROUP BY 1")
def _(spark, d):
    return measures.memory(*_log(spark, d))


@query("meas_effective_epochs", f"WITH {sql.SUPPLIER}, {_PICKED} SELECT epoch, sum(n) OVER (ORDER BY epoch) / 8.0::DOUBLE AS eff_epoch FROM (SELECT epoch, count(*) AS n FROM k GROUP BY 1)")
def _(spark, d):
    return measures.effective_epochs(_log(spark, d)[0], 4, 2)


@query("meas_refresh_counts", f"WITH {sql.SUPPLIER}, {_PICKED} SELECT cb, rb, count(*) AS refreshes FROM k GROUP BY 1, 2")
def _(spark, d):
    return measures.refresh_counts(_log(spark, d)[0])


#: a made-up history from the tables: a run per event type, an epoch per day, decibels from counts
_HIST = "h AS (SELECT event_type AS run, day(ts)::INT AS epoch, round(log10(sum(count(*)) OVER (PARTITION BY event_type ORDER BY day(ts))) * 10, 6) AS gap_db, count(*)::DOUBLE AS snr_db FROM events GROUP BY event_type, day(ts))"


def history(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    ev = spark.read.parquet(f"{d}/events.parquet").groupBy(F.col("event_type").alias("run"), F.dayofmonth("ts").alias("epoch")).agg(F.count("*").alias("n"))
    total = F.sum("n").over(Window.partitionBy("run").orderBy("epoch"))
    return ev.select("run", "epoch", F.round(F.log10(total) * 10, 6).alias("gap_db"), F.col("n").cast("double").alias("snr_db"))


@query("meas_repeat_mean", f"WITH {_HIST} SELECT epoch, round(avg(snr_db), 6) AS snr_db, round(avg(gap_db), 6) AS gap_db FROM h GROUP BY 1")
def _(spark, d):
    return rounded(measures.mean_history(history(spark, d)), "snr_db", "gap_db", digits=6)


@query("meas_sampler_gain", f"WITH {_HIST} SELECT epoch, round(avg(snr_db) FILTER (WHERE run < 'm') - avg(snr_db) FILTER (WHERE run >= 'm'), 6) AS gain_db FROM h GROUP BY 1 HAVING count(*) FILTER (WHERE run < 'm') > 0 AND count(*) FILTER (WHERE run >= 'm') > 0")
def _(spark, d):
    h = history(spark, d)
    return rounded(measures.sampler_gain(h.where("run < 'm'"), h.where("run >= 'm'")), "gain_db", digits=6)


@query(
    "meas_plateaus",
    f"""WITH {_HIST}, f AS (SELECT run, epoch, epoch - row_number() OVER (PARTITION BY run ORDER BY epoch) AS island FROM
      (SELECT *, gap_db - lag(gap_db) OVER (PARTITION BY run ORDER BY epoch) AS gain, max(gap_db) OVER (PARTITION BY run) AS best FROM h) WHERE gain < 0.3 AND gap_db < best - 0.3)
    SELECT run, min(epoch)::INT AS first_epoch, max(epoch)::INT AS last_epoch FROM f GROUP BY run, island HAVING count(*) >= 2""",
)
def _(spark, d):
    return measures.plateaus(history(spark, d), 0.3, 2)


@query("meas_diverged", f"WITH {_HIST} SELECT run, arg_max(gap_db, epoch) < arg_min(gap_db, epoch) AS diverged FROM h GROUP BY run")
def _(spark, d):
    return measures.diverged(history(spark, d))


@query("meas_epochs_to", f"WITH {_HIST} SELECT run, min(epoch) FILTER (WHERE gap_db >= 30) AS epoch FROM h GROUP BY run")
def _(spark, d):
    return measures.epochs_to(history(spark, d), 30.0)


# --- invariants: rows that break them --------------------------------------------------------------


def _broken(df: DataFrame) -> DataFrame:
    return df.agg(F.count("*").alias("violations"))


_NONE = "SELECT count(*) AS violations FROM orders WHERE o_orderkey IS NULL"


@query("inv_block_drop", _NONE)
def _(spark, d):
    """With step 1, a block's squared residual falls by exactly (g.g)^2 / |A g|^2."""
    p = one_round(spark, d)
    m = p["mu"].select("cb", "grp", "num", "den", (F.col("num") / F.col("den")).alias("mu"))
    after = p["f"].join(m, ["cb", "grp"]).join(p["r"].select("row_id", "r"), "row_id")
    drop = after.groupBy("cb", "grp", "num", "den").agg(F.sum(F.col("r") * F.col("r")).alias("a"), F.sum(F.pow(F.col("r") - F.col("mu") * F.col("ag"), F.lit(2))).alias("b"))
    return _broken(drop.where("abs((a - b) - num * num / den) > 1e-9 * a"))


@query("inv_residual_update", _NONE)
def _(spark, d):
    """The updated residual equals the recomputed one."""
    s = supplier(spark, d)
    picks = dens.entry_density(s.entries, s.rows).where("cb = 1 AND rb = 2").withColumn("grp", F.lit(0))
    new = solver.round_of(s, solver.start(s), picks, SolveSpec(), 1)
    again = step.true_residual(s.entries, s.y, new.x).select("row_id", F.col("r").alias("r2"))
    return _broken(new.r.where("rb = 2").join(again, "row_id").where("abs(r - r2) > 1e-6 * (1 + abs(r2))"))


@query("inv_probabilities", _NONE)
def _(spark, d):
    return _broken(term_density(spark, d)[1].groupBy("cb").agg(F.sum("p").alias("p")).where("abs(p - 1) > 1e-9"))


@query("inv_picks", _NONE)
def _(spark, d):
    """No row block twice, and exactly min(take, blocks with entries) picks."""
    s, den = term_density(spark, d)
    p = sampling.draw_row_blocks(den, s.rows, 20, SolveSpec(row_fraction=0.5), 2)
    some = den.where("p_s > 0").groupBy("cb").agg(F.least(F.count("*"), F.lit(10)).alias("want"))
    return _broken(p.groupBy("cb").agg(F.count("*").alias("n"), F.countDistinct("rb").alias("k")).join(some, "cb", "full").where("n IS DISTINCT FROM want OR k IS DISTINCT FROM n"))


@query("inv_fixed_point", _NONE)
def _(spark, d):
    """At the truth, with the truth's projections, nothing moves."""
    s = supplier(spark, d)
    z = s.entries.join(s.x_true().select("col_id", "x"), "col_id").groupBy("cb", "rb", "row_id").agg(F.sum(F.col("val") * F.col("x")).alias("z"))
    st = solver.State(s.x_true(), z, step.surrogate_residual(s.y, z))
    picks = dens.entry_density(s.entries, s.rows).withColumn("grp", F.col("rb"))
    new = solver.round_of(s, st, picks, SolveSpec(), 1)
    return _broken(new.x.join(s.x_true().select("col_id", F.col("x").alias("t")), "col_id").where("abs(x - t) > 1e-6"))


@query("inv_scaling", _NONE)
def _(spark, d):
    """Observations times c give x times c."""
    s = supplier(spark, d)
    big = replace(s, y=s.y.withColumn("y", F.col("y") * 8))
    a, b = (solver.epochs_lazily(q, SolveSpec(), 4, [0, 1]).x for q in (s, big))
    return _broken(a.join(b.select("col_id", F.col("x").alias("x8")), "col_id").where("abs(8 * x - x8) > 1e-6 * (1 + abs(x8))"))


@query("inv_untouched", _NONE)
def _(spark, d):
    """Column blocks that were not drawn keep their values."""
    s = supplier(spark, d)
    picks = dens.entry_density(s.entries, s.rows).where("cb = 1").withColumn("grp", F.col("rb"))
    return _broken(solver.round_of(s, solver.start(s), picks, SolveSpec(), 1).x.where("cb = 0 AND x <> 0"))


@query("inv_strategies", _NONE)
def _(spark, d):
    """Relational and packed rounds agree."""
    s = supplier(spark, d)
    a, b = (solver.epochs_lazily(s, SolveSpec(strategy=k), 4, [0, 1]).x for k in ("relational", "packed"))
    return _broken(a.join(b.select("col_id", F.col("x").alias("xb")), "col_id").where("abs(x - xb) > 1e-6 * (1 + abs(x))"))


@query("inv_single_block", _NONE)
def _(spark, d):
    """One row block and one column block: steepest descent with exact line search."""
    s = supplier(spark, d)
    one = replace(s, entries=s.entries.withColumns({"cb": F.lit(0), "rb": F.lit(0)}), y=s.y.withColumn("rb", F.lit(0)), rows=s.rows.withColumn("rb", F.lit(0)), cols=s.cols.withColumn("cb", F.lit(0)))
    a = solver.epochs_lazily(one, SolveSpec(), 1, [0]).x
    b = base.col_action(one, one.x_zero(), [0], "steepest").select("col_id", F.col("x").alias("xb"))
    return _broken(a.join(b, "col_id").where("abs(x - xb) > 1e-6 * (1 + abs(x))"))


@query("inv_full_gradient", _NONE)
def _(spark, d):
    """All row blocks in one group: a block's gradient is the full gradient's part."""
    p = one_round(spark, d, 4)
    full = p["s"].entries.join(p["r"].select("row_id", "r"), "row_id").groupBy("col_id").agg(F.sum(F.col("val") * F.col("r")).alias("full"))
    return _broken(p["xg"].join(full, "col_id").where("abs(g - full) > 1e-6 * (1 + abs(full))"))


@query("inv_column_case", _NONE)
def _(spark, d):
    """One row block, refreshed after each column block: the surrogate residual is the true one."""
    s = supplier(spark, d)
    one = replace(s, entries=s.entries.withColumn("rb", F.lit(0)), y=s.y.withColumn("rb", F.lit(0)), rows=s.rows.withColumn("rb", F.lit(0)))
    st = solver.epochs_lazily(one, SolveSpec(), 1, [0, 1])
    again = step.true_residual(one.entries, one.y, st.x).select("row_id", F.col("r").alias("r2"))
    return _broken(st.r.join(again, "row_id").where("abs(r - r2) > 1e-6 * (1 + abs(r2))"))


@query("inv_relabelled", _NONE)
def _(spark, d):
    """New names for rows, columns and blocks change nothing but names."""
    s = supplier(spark, d)
    flip = {"cb": 1 - F.col("cb"), "rb": 3 - F.col("rb")}
    other = replace(s, entries=s.entries.withColumns(flip), y=s.y.withColumn("rb", flip["rb"]), rows=s.rows.withColumn("rb", flip["rb"]), cols=s.cols.withColumn("cb", flip["cb"]))
    a, b = (solver.epochs_lazily(q, SolveSpec(refresh="epoch"), 4, [0, 1]).x for q in (s, other))
    return _broken(a.join(b.select("col_id", F.col("x").alias("xb")), "col_id").where("abs(x - xb) > 1e-6 * (1 + abs(x))"))
