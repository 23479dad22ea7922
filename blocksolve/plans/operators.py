"""Queries on the relational operators around the solver, each with its SQL."""

from __future__ import annotations

import math
import uuid

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from blocksolve.functions.hashing import gaussian, uniform
from blocksolve.operators import relational as rel
from blocksolve.operators.packed import pack
from blocksolve.plans import sql
from blocksolve.plans.blocks import rounded, supplier
from blocksolve.sources import generated, store, systems
from blocksolve.sources.tables import table

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, text: str | None = None):
    def add(f):
        QUERIES[f"op_{name}"] = f
        if text:
            SQL[f"op_{name}"] = text
        return f

    return add


@query("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '2001-06-01' AND l_returnflag = 'R'")
def _(spark, d):
    return table(spark, d, "lineitem").where("l_shipdate >= TIMESTAMP'2001-06-01' AND l_returnflag = 'R'").select("l_orderkey", "l_quantity")


@query("predicates", "SELECT count(*) FILTER (WHERE o_orderpriority LIKE '1%') AS urgent, count(*) FILTER (WHERE regexp_matches(o_orderpriority, 'LOW|MEDIUM')) AS calm, count(*) FILTER (WHERE o_orderdate BETWEEN TIMESTAMP '1995-01-01' AND TIMESTAMP '1996-01-01') AS y95, count(*) FILTER (WHERE NULLIF(o_orderstatus, 'F') IS NOT DISTINCT FROM NULL) AS done FROM orders")
def _(spark, d):
    o = table(spark, d, "orders")
    status = F.when(F.col("o_orderstatus") != "F", F.col("o_orderstatus"))
    return o.agg(
        F.count_if(F.col("o_orderpriority").like("1%")).alias("urgent"), F.count_if(F.col("o_orderpriority").rlike("LOW|MEDIUM")).alias("calm"),
        F.count_if(F.col("o_orderdate").between("1995-01-01", "1996-01-01")).alias("y95"), F.count_if(status.eqNullSafe(F.lit(None))).alias("done"),
    )


@query("block_ids", "SELECT o_orderkey, (o_orderkey % 8)::INT AS by_key, floor(o_totalprice / 50000)::INT AS by_range, ntile(7) OVER (ORDER BY o_totalprice, o_orderkey)::INT AS by_tile, (('0x' || substr(md5('0|' || o_orderkey), 1, 8))::BIGINT % 5)::INT AS by_hash FROM orders")
def _(spark, d):
    o = table(spark, d, "orders", "o_orderkey", "o_totalprice")
    hashed = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit("0"), F.col("o_orderkey").cast("string"))), 1, 8), 16, 10).cast("bigint")
    return o.select("o_orderkey", F.pmod("o_orderkey", F.lit(8)).cast("int").alias("by_key"), F.floor(F.col("o_totalprice") / 50000).cast("int").alias("by_range"), F.ntile(7).over(Window.orderBy("o_totalprice", "o_orderkey")).alias("by_tile"), F.pmod(hashed, F.lit(5)).cast("int").alias("by_hash"))


@query("rows_without_entries", "SELECT o_orderkey, coalesce(sum(l_quantity), 0.0) AS y FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark, d):
    s = table(spark, d, "lineitem", "l_orderkey", "l_quantity").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("y"))
    return table(spark, d, "orders", "o_orderkey").join(s, F.col("o_orderkey") == F.col("l_orderkey"), "left").select("o_orderkey", F.coalesce("y", F.lit(0.0)).alias("y"))


@query("semi_join", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_discount > 0.09)")
def _(spark, d):
    return table(spark, d, "orders", "o_orderkey").join(table(spark, d, "lineitem", "l_orderkey", "l_discount").where("l_discount > 0.09"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")


@query("anti_join", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def _(spark, d):
    return table(spark, d, "orders", "o_orderkey").join(table(spark, d, "lineitem", "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query("range_join", "SELECT w.s AS s, count(*) AS n, round(sum(l_quantity), 2) AS q FROM (SELECT range * 30 AS s FROM range(0, 80)) w JOIN lineitem ON datediff('day', DATE '1995-01-01', l_shipdate::DATE) BETWEEN w.s AND w.s + 44 GROUP BY 1")
def _(spark, d):
    p = table(spark, d, "lineitem", "l_shipdate", "l_quantity").select(F.expr("datediff(l_shipdate, DATE'1995-01-01')").alias("day"), "l_quantity")
    w = spark.range(80).select((F.col("id") * 30).alias("s")).withColumn("e", F.col("s") + 44)
    return rel.range_join(p, w, "day", "s", "e", 45).groupBy("s").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@query("as_of_join", "SELECT a.event_id, max_by(b.event_id, (b.ts, b.event_id)) AS then FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_type = 'view' AND b.ts <= a.ts WHERE a.event_type = 'purchase' GROUP BY 1")
def _(spark, d):
    e = table(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    right = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("then"))
    return rel.as_of(e.where("event_type = 'purchase'").select("user_id", "ts", "event_id"), right, ["user_id"], "ts", "then").select("event_id", "then")


@query("interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND epoch(b.ts)::BIGINT - epoch(a.ts)::BIGINT <= 600")
def _(spark, d):
    e = table(spark, d, "events", "event_id", "ts", "user_id")
    return rel.interval_join(e.select("user_id", F.col("ts").alias("ta"), F.col("event_id").alias("a")), e.select("user_id", F.col("ts").alias("tb"), F.col("event_id").alias("b")), "user_id", "ta", "tb", 600).select("a", "b")


@query("theta_join", "SELECT s_suppkey, count(*) AS n FROM supplier JOIN nation ON s_nationkey < n_nationkey AND s_acctbal > n_nationkey * 100 GROUP BY 1")
def _(spark, d):
    n = table(spark, d, "nation", "n_nationkey")  # 25 rows, whatever the scale
    return table(spark, d, "supplier", "s_suppkey", "s_nationkey", "s_acctbal").join(F.broadcast(n), F.expr("s_nationkey < n_nationkey AND s_acctbal > n_nationkey * 100")).groupBy("s_suppkey").agg(F.count("*").alias("n"))


@query("full_join", "SELECT coalesce(a.k, b.k) AS k, a.n AS a, b.n AS b FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 9000 GROUP BY 1) b ON a.k = b.k")
def _(spark, d):
    a = table(spark, d, "customer", "c_nationkey").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("a"))
    b = table(spark, d, "supplier").where("s_acctbal > 9000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("b"))
    return a.join(b, "k", "full")


@query("aggregates", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS q, round(avg(l_quantity), 6) AS a, min(l_quantity) AS lo, max(l_quantity) AS hi, count(DISTINCT l_partkey) AS parts, round(stddev(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS c, round(quantile_cont(l_quantity, 0.5), 6) AS med, round(regr_slope(l_quantity, l_extendedprice), 9) AS slope FROM lineitem GROUP BY 1")
def _(spark, d):
    q = F.col("l_quantity")
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.count("*").alias("n"), F.round(F.sum(q), 2).alias("q"), F.round(F.avg(q), 6).alias("a"), F.min(q).alias("lo"), F.max(q).alias("hi"), F.countDistinct("l_partkey").alias("parts"), F.round(F.stddev(q), 6).alias("sd"),
        F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c"), F.round(F.percentile(q, F.lit(0.5)), 6).alias("med"), F.round(F.regr_slope("l_quantity", "l_extendedprice"), 9).alias("slope"),
    )


@query("exact_decimals", "SELECT l_suppkey, sum(l_extendedprice::DECIMAL(18, 2))::DOUBLE AS total FROM lineitem GROUP BY 1")
def _(spark, d):
    return table(spark, d, "lineitem", "l_suppkey", "l_extendedprice").groupBy("l_suppkey").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("total"))


@query("approx_distinct")
def _(spark, d):
    return table(spark, d, "lineitem", "l_returnflag", "l_partkey").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("window_ranks", "SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, row_number() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS rn FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def _(spark, d):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    long = lambda c: c.cast("bigint")
    return table(spark, d, "part").select("p_partkey", long(F.rank().over(w)).alias("r"), long(F.dense_rank().over(w)).alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"), long(F.row_number().over(Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"))).alias("rn"))


@query("window_frames", "SELECT d, n, sum(n) OVER (ORDER BY d)::BIGINT AS upto, round(avg(n) OVER (ORDER BY d ROWS BETWEEN 6 PRECEDING AND CURRENT ROW), 6) AS week, sum(n) OVER (ORDER BY d RANGE BETWEEN INTERVAL 2 DAY PRECEDING AND CURRENT ROW)::BIGINT AS three, n - lag(n) OVER (ORDER BY d) AS step FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS d, count(*) AS n FROM events GROUP BY 1)")
def _(spark, d):
    day = table(spark, d, "events", "ts").groupBy(F.date_trunc("day", "ts").alias("d")).agg(F.count("*").alias("n"))
    w = Window.orderBy("d")
    day.createOrReplaceTempView("block_days")
    three = spark.sql("SELECT d, sum(n) OVER (ORDER BY d RANGE BETWEEN INTERVAL 2 DAYS PRECEDING AND CURRENT ROW) AS three FROM block_days")
    return day.select("d", "n", F.sum("n").over(w).alias("upto"), F.round(F.avg("n").over(w.rowsBetween(-6, 0)), 6).alias("week"), (F.col("n") - F.lag("n").over(w)).alias("step")).join(three, "d")


@query("top_k", "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20")
def _(spark, d):
    return table(spark, d, "part", "p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").limit(20)


@query("top_k_per_group", "SELECT p_brand, p_partkey FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def _(spark, d):
    r = F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey"))
    return table(spark, d, "part").withColumn("r", r).where("r <= 3").select("p_brand", "p_partkey")


@query("set_operations", "SELECT 'union' AS op, count(*) AS n FROM (SELECT l_partkey FROM lineitem UNION SELECT p_partkey FROM part) UNION ALL SELECT 'both', count(*) FROM (SELECT l_partkey FROM lineitem INTERSECT SELECT p_partkey FROM part WHERE p_size > 25) UNION ALL SELECT 'less', count(*) FROM (SELECT p_partkey FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 40)")
def _(spark, d):
    line, part = table(spark, d, "lineitem", "l_partkey", "l_quantity"), table(spark, d, "part", "p_partkey", "p_size")
    of = lambda df, name: df.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n")
    l, p = line.select("l_partkey"), part.select("p_partkey")
    return of(l.union(p).distinct(), "union").union(of(l.intersect(part.where("p_size > 25").select("p_partkey")), "both")).union(of(p.subtract(line.where("l_quantity > 40").select("l_partkey")), "less"))


@query("math", "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS a, round(log10(p_retailprice), 6) AS b, round(ln(p_retailprice), 6) AS c, round(sin(p_size), 6) AS d, round(atan2(p_size, p_retailprice), 6) AS e, greatest(p_size, 25)::INT AS f, sign(p_size - 25)::INT AS g FROM part")
def _(spark, d):
    x, s = F.col("p_retailprice"), F.col("p_size")
    return table(spark, d, "part").select("p_partkey", F.round(F.sqrt(x), 6).alias("a"), F.round(F.log10(x), 6).alias("b"), F.round(F.ln(x), 6).alias("c"), F.round(F.sin(s), 6).alias("d"), F.round(F.atan2(s.cast("double"), x), 6).alias("e"), F.greatest(s, F.lit(25)).alias("f"), F.signum(s - 25).cast("int").alias("g"))


@query("dates", "SELECT o_orderkey, date_trunc('quarter', o_orderdate)::TIMESTAMP AS q, year(o_orderdate)::INT AS y, datediff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS n, (o_orderdate + INTERVAL 10 DAY)::TIMESTAMP AS later FROM orders")
def _(spark, d):
    o = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.date_trunc("quarter", o).alias("q"), F.year(o).alias("y"), F.datediff(o, F.lit("1992-01-01").cast("date")).alias("n"), (o + F.expr("INTERVAL 10 DAYS")).alias("later"))


@query("strings", "SELECT page_id, regexp_extract(url, 'https?://([^/]+)', 1) AS host, length(html)::INT AS n, md5(url) AS h, substr(lower(url), 1, 12) AS s FROM pages")
def _(spark, d):
    return table(spark, d, "pages").select("page_id", F.regexp_extract("url", "https?://([^/]+)", 1).alias("host"), F.length("html").alias("n"), F.md5("url").alias("h"), F.substring(F.lower("url"), 1, 12).alias("s"))


@query("arrays", "SELECT vec_id, round(list_sum([x::DOUBLE * x::DOUBLE for x in embedding]), 5) AS norm, len([x for x in embedding if x > 0])::INT AS positive, round(embedding[1:8][3]::DOUBLE, 6) AS third FROM embeddings")
def _(spark, d):
    return table(spark, d, "embeddings").select("vec_id", F.round(rel.dot("embedding", "embedding"), 5).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.slice("embedding", 1, 8)[2].cast("double"), 6).alias("third"))


@query("maps", f"WITH {sql.SUPPLIER} SELECT row_id, count(*)::INT AS n, round(sum(2 * val), 4) AS doubled FROM entries GROUP BY 1")
def _(spark, d):
    m = rel.sparse_rows(supplier(spark, d).entries)
    two = F.map_values(F.transform_values("row", lambda k, v: 2 * v))
    return m.select("row_id", F.size("row").alias("n"), F.round(F.aggregate(two, F.lit(0.0), lambda a, v: a + v), 4).alias("doubled"))


@query("json", "SELECT event_id, json_extract(props, '$.k')::INT AS k FROM events")
def _(spark, d):
    return table(spark, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k INT")["k"].alias("k"))


@query("hash_uniform", f"SELECT o_orderkey, round({sql.uniform(7, '3', 'o_orderkey')}, 9) AS u, round(sqrt(-2 * ln({sql.uniform(7, 'o_orderkey', '1')})) * cos(2 * pi() * {sql.uniform(7, 'o_orderkey', '2')}), 6) AS g FROM orders")
def _(spark, d):
    k = F.col("o_orderkey")
    return table(spark, d, "orders", "o_orderkey").select("o_orderkey", F.round(uniform(7, 3, k), 9).alias("u"), F.round(gaussian(7, k), 6).alias("g"))


@query("packed_blocks", f"WITH {sql.SUPPLIER} SELECT cb, rb, count(DISTINCT row_id)::INT AS n_rows, count(DISTINCT col_id)::INT AS n_cols, count(*)::INT AS nnz FROM entries GROUP BY 1, 2")
def _(spark, d):
    return pack(supplier(spark, d).entries).select("cb", "rb", F.size("rows").alias("n_rows"), F.size("cols").alias("n_cols"), F.size("val").alias("nnz"))


def _place(spark, name: str) -> str:
    return f"{store.shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


@query("block_store", f"WITH {sql.SUPPLIER} SELECT cb, rb, row_id, col_id, val FROM entries WHERE cb = 1 AND rb = 2")
def _(spark, d):
    path = _place(spark, "blocks")
    store.write_blocks(supplier(spark, d).entries, path, 4)
    return store.read_blocks(spark, path).where("cb = 1 AND rb = 2")


@query("versioned_state", "SELECT s_suppkey AS col_id, s_acctbal + 3.0 AS x FROM supplier")
def _(spark, d):
    path = _place(spark, "state")
    for epoch in (1, 2, 3):
        store.write_epoch(table(spark, d, "supplier").select(F.col("s_suppkey").alias("col_id"), (F.col("s_acctbal") + float(epoch)).alias("x")), path, epoch)
    return spark.read.parquet(f"{path}/epoch=3")


@query("coordinate_text", f"WITH {sql.SUPPLIER} SELECT row_id, col_id, val FROM entries")
def _(spark, d):
    path = _place(spark, "coordinates")
    store.write_coordinates(supplier(spark, d).entries, path)
    return store.read_coordinates(spark, path)


@query("csv_json_round_trip", "SELECT s_suppkey AS col_id, s_acctbal AS x FROM supplier")
def _(spark, d):
    a, b = _place(spark, "csv"), _place(spark, "json")
    table(spark, d, "supplier").select(F.col("s_suppkey").alias("col_id"), F.col("s_acctbal").alias("x")).write.csv(a, header=True)
    spark.read.schema("col_id bigint, x double").csv(a, header=True).write.json(b)
    return spark.read.schema("col_id bigint, x double").json(b)


@query("generated_source", f"SELECT view, count(*) AS rays, round(avg(29.0 * cos(view * {2 * math.pi / 36!r} + 0.001)), 6) AS sx FROM ({sql.readings(36, 47)}) WHERE view IN (3, 5) GROUP BY 1")
def _(spark, d):
    """Customers as rays, placed by the Python data source; the filter on views reaches it."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(generated.FanRays)
    made = spark.read.format("fan_rays").option("views", 36).option("dets", 47).option("radius", 29).load().where("view IN (3, 5)")
    read = systems.readings(spark, d, 36, 47).select("view", "det")
    return rounded(read.join(made.select("view", "det", "sx"), ["view", "det"]).groupBy("view").agg(F.count("*").alias("rays"), F.avg("sx").alias("sx")), "sx", digits=6)


@query("sql_surface", "SELECT (s_nationkey % 2)::INT AS cb, count(*) AS n FROM supplier GROUP BY 1")
def _(spark, d):
    s = supplier(spark, d)
    s.cols.createOrReplaceTempView("block_columns")
    return spark.sql("SELECT cb, count(*) AS n FROM block_columns GROUP BY cb")


@query("grouped_udf", "WITH " + sql.SUPPLIER + " SELECT cb, rb, round(sum(val * val), 2) + 0.0 AS mass FROM entries GROUP BY 1, 2")
def _(spark, d):
    """A block's squared mass by an aggregate function over Arrow batches, as a user's own measure would come."""

    @F.pandas_udf("double")
    def mass(val: pd.Series) -> float:
        return float((val * val).sum())

    return rounded(supplier(spark, d).entries.groupBy("cb", "rb").agg(mass("val").alias("mass")), "mass", digits=2)


@F.udtf(returnType="part int, first bigint, last bigint")
class Runs:
    """Cuts 0..n-1 into equal runs."""

    def eval(self, n: int, parts: int):
        for k in range(parts):
            first, last = -(-k * n // parts), -(-(k + 1) * n // parts) - 1
            if first <= last:
                yield k, first, last


@query("table_function", "SELECT r_regionkey, k::INT AS part, (k * 25 + 3) // 4 AS first, ((k + 1) * 25 + 3) // 4 - 1 AS last FROM region, range(0, 4) q(k)")
def _(spark, d):
    spark.udtf.register("runs_of", Runs)
    table(spark, d, "region").createOrReplaceTempView("run_regions")
    return spark.sql("SELECT r_regionkey, t.* FROM run_regions, LATERAL runs_of(25, 4) t")


@query("sql_functions", "SELECT (s_suppkey % 3)::INT AS cb, count(*) AS n FROM supplier GROUP BY 1")
def _(spark, d):
    """Block numbers as a function of SQL."""

    @F.pandas_udf("int")
    def block(key: pd.Series, parts: pd.Series) -> pd.Series:
        return (key % parts).astype("int32")

    spark.udf.register("block_number", block)
    table(spark, d, "supplier").createOrReplaceTempView("numbered_suppliers")
    return spark.sql("SELECT block_number(s_suppkey, 3) AS cb, count(*) AS n FROM numbered_suppliers GROUP BY 1")


@query("arbitrary_partition", "SELECT count(DISTINCT l_suppkey) AS n_cols, 7::BIGINT AS most_blocks FROM lineitem")
def _(spark, d):
    """Columns dealt to seven blocks by hash instead of by nation: every column in one block."""
    s = systems.partition_by(supplier(spark, d), cb=F.col("col_id"), parts=7)
    per = s.entries.select("cb", "col_id").distinct()
    one = per.groupBy("col_id").agg(F.count("*").alias("k"))
    return one.agg(F.sum(F.when(F.col("k") == 1, 1)).alias("n_cols"), F.lit(7).cast("long").alias("most_blocks"))
