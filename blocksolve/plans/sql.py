"""SQL of the catalogue's systems and of unrolled epochs, for the comparison engine. Written apart from the DataFrame code."""

from __future__ import annotations

#: the order-by-supplier system: 4 row blocks by order key, 2 column blocks by nation
SUPPLIER = """
rws AS MATERIALIZED (SELECT o_orderkey AS row_id, (o_orderkey % 4)::INT AS rb FROM orders),
cols AS MATERIALIZED (SELECT s_suppkey AS col_id, (s_nationkey % 2)::INT AS cb, s_acctbal + 0.0 AS x_true FROM supplier),
raw AS (SELECT l_orderkey AS row_id, l_suppkey AS col_id, sum(l_quantity) AS val FROM lineitem GROUP BY 1, 2),
entries AS MATERIALIZED (SELECT cb, rb, row_id, col_id, val FROM raw JOIN rws USING (row_id) JOIN cols USING (col_id) WHERE val <> 0),
obs AS (SELECT row_id, sum(val * x_true) AS y FROM entries JOIN cols USING (col_id) GROUP BY 1),
y AS MATERIALIZED (SELECT rb, rws.row_id, coalesce(obs.y, 0.0) AS y FROM rws LEFT JOIN obs ON rws.row_id = obs.row_id),
density AS MATERIALIZED (SELECT cb, rb, rb AS view, p_s, sum(p_s) OVER (PARTITION BY cb) AS p_t, p_s / sum(p_s) OVER (PARTITION BY cb) AS p
            FROM (SELECT cb, rb, count(*)::DOUBLE AS p_s FROM entries GROUP BY 1, 2))"""

#: documents by frequent terms: a row block per language and source class, a column block per home language
TERMS = """
langs AS (SELECT lang, (dense_rank() OVER (ORDER BY lang) - 1)::INT AS l FROM (SELECT DISTINCT lang FROM documents)),
tok AS (SELECT doc_id, lang, unnest(string_split_regex(lower(text), '\\s+')) AS term FROM documents),
cnt AS MATERIALIZED (SELECT doc_id, lang, term, count(*) AS n FROM tok WHERE term <> '' GROUP BY ALL),
home AS (SELECT term, sum(df) AS df, arg_max(lang, df * 10 + l) AS home
         FROM (SELECT term, c.lang, l, count(*) AS df FROM cnt c JOIN langs USING (lang) GROUP BY 1, 2, 3) GROUP BY term HAVING sum(df) >= 20),
rws AS MATERIALIZED (SELECT doc_id AS row_id, (l * 5 + regexp_extract(source, '(\\d+)', 1)::INT % 5)::INT AS rb, l AS view FROM documents JOIN langs USING (lang)),
cols AS MATERIALIZED (SELECT ('0x' || substr(md5(term), 1, 12))::BIGINT AS col_id, l AS cb FROM home JOIN langs ON home = lang),
entries AS MATERIALIZED (SELECT cb, rb, row_id, col_id, val FROM
   (SELECT doc_id AS row_id, ('0x' || substr(md5(term), 1, 12))::BIGINT AS col_id, sum(n)::DOUBLE AS val FROM cnt GROUP BY 1, 2) JOIN rws USING (row_id) JOIN cols USING (col_id)),
density AS MATERIALIZED (SELECT cb, rb, view, p_s, sum(p_s) OVER (PARTITION BY cb) AS p_t, p_s / sum(p_s) OVER (PARTITION BY cb) AS p
            FROM (SELECT cb, rb, min(view) AS view, count(*)::DOUBLE AS p_s FROM entries JOIN rws USING (row_id, rb) GROUP BY 1, 2))"""


def readings(views: int, dets: int) -> str:
    """Customers as rays: the nation is the view, the balance the detector's cell."""
    return f"""SELECT c_custkey AS row_id, (c_nationkey % {views})::INT AS view, least(greatest(floor((c_acctbal + 1000.0) * {dets} / 11000.0), 0), {dets - 1})::INT AS det
      FROM customer WHERE c_nationkey IS NOT NULL AND c_acctbal IS NOT NULL"""


def uniform(seed: int, *keys: str) -> str:
    parts = " || '|' || ".join([f"'{seed}'", *[f"({k})::VARCHAR" for k in keys]])
    return f"((('0x' || substr(md5({parts}), 1, 8))::BIGINT + 0.5) / 4294967296.0)"


def picks(epoch: int, take: int, weight: str = "p", group: int = 1, seed: int = 0, where: str = "true") -> str:
    """cb, rb, pick_rank, grp, p_s, p_t of the weighted race."""
    return f"""SELECT cb, rb, view, pick_rank::INT AS pick_rank, ((pick_rank - 1) // {group})::INT AS grp, p_s, p_t FROM
      (SELECT *, row_number() OVER (PARTITION BY cb ORDER BY -ln({uniform(seed, str(epoch), 'cb', 'rb')}) / ({weight}), rb) AS pick_rank
       FROM density WHERE p_s > 0 AND {where}) WHERE pick_rank <= {take}"""


def epochs(rounds: list[tuple[str, float]], last: str, ridge: float = 0.0, residual: str = "surrogate", beta: str | None = None, averages: bool = True) -> str:
    """CTEs of unrolled rounds, each (picks SQL, damped base). ``beta``: expression over a group (default: the base)."""
    ctes = ["x0 AS MATERIALIZED (SELECT cb, col_id, 0.0::DOUBLE AS x FROM cols)", "z0 AS MATERIALIZED (SELECT 0 AS cb, 0 AS rb, 0::BIGINT AS row_id, 0.0::DOUBLE AS z WHERE false)"]
    for t, (pick, base) in enumerate(rounds, 1):
        s = t - 1
        b = (beta or "{base}").format(base=repr(float(base)))
        r = f"SELECT rb, y.row_id, y - coalesce(s.z, 0) AS r FROM y LEFT JOIN (SELECT row_id, sum(z) AS z FROM z{s} GROUP BY 1) s ON y.row_id = s.row_id"
        if residual == "true":
            r = f"SELECT rb, y.row_id, y - coalesce(s.z, 0) AS r FROM y LEFT JOIN (SELECT row_id, sum(val * x) AS z FROM entries JOIN x{s} USING (cb, col_id) GROUP BY 1) s ON y.row_id = s.row_id"
        ctes += [
            f"k{t} AS MATERIALIZED ({pick})",
            f"r{t} AS MATERIALIZED ({r})",
            f"g{t} AS MATERIALIZED (SELECT cb, grp, col_id, x, g - {ridge!r} * x AS g FROM (SELECT e.cb, k.grp, e.col_id, sum(val * r) AS g FROM entries e JOIN k{t} k USING (cb, rb) JOIN r{t} r USING (row_id) GROUP BY 1, 2, 3) JOIN x{s} USING (cb, col_id))",
            f"f{t} AS MATERIALIZED (SELECT e.cb, k.grp, e.rb, e.row_id, sum(val * x) AS ax, sum(val * g) AS ag FROM entries e JOIN k{t} k USING (cb, rb) JOIN g{t} g ON g.cb = e.cb AND g.grp = k.grp AND g.col_id = e.col_id GROUP BY 1, 2, 3, 4)",
            f"""m{t} AS MATERIALIZED (SELECT cb, grp, CASE WHEN den + {ridge!r} * num > 0 THEN beta * num / (den + {ridge!r} * num) ELSE 0 END AS mu, beta, num, den FROM
              (SELECT cb, grp, {b} AS beta FROM k{t} GROUP BY 1, 2) JOIN (SELECT cb, grp, sum(g * g) AS num FROM g{t} GROUP BY 1, 2) USING (cb, grp) JOIN (SELECT cb, grp, sum(ag * ag) AS den FROM f{t} GROUP BY 1, 2) USING (cb, grp))""",
            f"""x{t} AS MATERIALIZED (SELECT x.cb, x.col_id, x.x + coalesce(d.d / v.v, 0) AS x FROM x{s} x LEFT JOIN (SELECT cb, col_id, sum(mu * g) AS d FROM g{t} JOIN m{t} USING (cb, grp) GROUP BY 1, 2) d ON x.cb = d.cb AND x.col_id = d.col_id
              LEFT JOIN (SELECT cb, count(DISTINCT grp) AS v FROM k{t} GROUP BY 1) v ON x.cb = v.cb)""",
            f"z{t} AS MATERIALIZED (SELECT * FROM z{s} ANTI JOIN k{t} USING (cb, rb) UNION ALL SELECT cb, rb, row_id, ax + mu * ag AS z FROM f{t} JOIN m{t} USING (cb, grp))",
        ]
    return "WITH " + SUPPLIER + ",\n" + ",\n".join(ctes) + "\n" + last
