"""Exact top-k search by inner product with a pivot-distance index.

Vectors are turned into whole numbers, floor(scale * x). With M the greatest squared norm, adding the
component sqrt(M - |x|^2) puts all vectors on one sphere, where the largest inner product is the
least distance: |q - x|^2 = |q|^2 + M - 2 q.x. Pivots are a bounded sample of the rows. Each vector is
keyed by its nearest pivot and its distance to it; in that order vectors form annuli of ``BLOCK`` rows, or of more, so
that there are about ``ANNULI`` at most: their bounds are broadcast.

Each query walks the annuli outwards: an annulus (p, lo..hi) is at least max(lo - d(q, p), d(q, p) - hi, 0) away, and the
annuli are taken in the order of that bound, in rounds of ``FACTOR`` times as many as the round before. After a round the k-th best score is the
query's radius; an annulus beyond it is never read, and a query stops once the next annulus is beyond (triangle inequality: no row
there can be better). A round sends each query to the annuli that it still needs, never rows to queries, so rows move once a round; queries that meet in
one annulus are dealt in chunks of ``CHUNK``. Scores are exact integers; only bounds are floating point, and they are widened by a safe margin.

How much is pruned depends on the data: on clustered vectors most annuli are never read (see the tests); on vectors spread evenly
over a sphere of many dimensions the k-th best is nearly as far as any row, and every exact method reads nearly all.

Defined results: vectors that are null, or hold null or non-finite components, take no part;
vectors shorter than the longest count as ending in zeros; ties go to the smaller id; rows that
repeat an id are rows of their own, but a query never meets rows of its own id; rows with a null id take no part; a repeated query
id is asked for its first vector only (in the order of components); whole numbers and scores beyond 64 bits are the nearest
64-bit number. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksolve.llm.common import drop_table, materialize, shuffle_partitions

PIVOTS, BLOCK, CHUNK, FACTOR = 64, 1024, 4096, 8
ANNULI = 1 << 16
CELLS = 1 << 22  # bounds (queries x annuli) that a task holds at once


def whole_numbers(rows: DataFrame, vec_id: str, vector: str, scale: int) -> DataFrame:
    """id, v (array<long>) of the rows that take part."""
    x = F.col(vector)
    fine = x.isNotNull() & F.forall(x, lambda e: e.isNotNull() & ~F.isnan(e.cast("double")) & (F.abs(e.cast("double")) != float("inf")))
    return rows.where(F.col(vec_id).isNotNull()).where(F.coalesce(fine, F.lit(False))).select(
        F.col(vec_id).cast("long").alias("id"), F.transform(x, lambda e: F.floor(F.lit(float(scale)) * e.cast("double"))).alias("v")
    )


def _matrix(column: pa.Array, dims: int) -> np.ndarray:
    n = np.diff(column.offsets.to_numpy())
    flat = column.flatten().to_numpy(zero_copy_only=False)
    out = np.zeros((len(column), dims), np.int64)
    row = np.repeat(np.arange(len(column)), n)
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(n) - n, n)] = flat
    return out


def _lifted(v: np.ndarray, top: float) -> np.ndarray:
    v = v.astype(np.float64)
    return np.hstack([v, np.sqrt(np.maximum(0.0, top - (v * v).sum(1)))[:, None]])


def _distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0.0, (a * a).sum(1)[:, None] + (b * b).sum(1)[None, :] - 2 * a @ b.T))


def keyed_by_pivot(rows: DataFrame, pivots: np.ndarray, top: float, dims: int) -> DataFrame:
    """id, v, pivot, far (distance to it)."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d = _distances(_lifted(_matrix(batch.column(1), dims), top), pivots)
            p = d.argmin(1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p.astype(np.int32)), pa.array(d[np.arange(len(p)), p])], ["id", "v", "pivot", "far"])

    return rows.mapInArrow(made, "id long, v array<long>, pivot int, far double")


def in_annuli(rows: DataFrame, size: int, name: str) -> DataFrame:
    """Adds block: runs of ``size`` rows in the order (pivot, far), inside ranges that Spark cuts, never across pivots."""
    n = shuffle_partitions(rows.sparkSession)
    dealt = rows.repartitionByRange(n, "pivot", "far", "id").select("*", F.spark_partition_id().alias("part"))
    place = F.row_number().over(Window.partitionBy("part", "pivot").orderBy("far", "id")) - 1
    return materialize(dealt.select("id", "v", "pivot", "far", F.xxhash64("part", "pivot", F.floor(place / size)).alias("block")), name)


def _scores(q: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Exact inner products, held to 64 bits."""
    most = lambda x: max(abs(int(x.max(initial=0))), abs(int(x.min(initial=0))), 1)
    big = most(q) * most(v) * max(1, q.shape[1])
    if big < 2**52:
        return (q.astype(float) @ v.T.astype(float)).astype(np.int64)
    if big < 2**62:
        return q @ v.T
    return np.clip(q.astype(object) @ v.T.astype(object), -(2**63), 2**63 - 1).astype(np.int64)


def _best(k: int, dims: int):
    """Rows grouped by (block, chunk): sorted, queries first. Of each query the k best rows of the group, none below its least."""

    def task(qid: np.ndarray, least: np.ndarray, q: np.ndarray, vid: np.ndarray, v: np.ndarray) -> pa.RecordBatch:
        s = _scores(q, v)
        good = (qid[:, None] != vid[None, :]) & (s >= least[:, None])
        m = min(k + 1, len(vid))
        if len(vid) > 4 * m:  # all rows that could be among the best, ties included
            edge = -np.partition(-np.where(good, s, np.iinfo(np.int64).min + 1), m - 1, axis=1)[:, m - 1]
            good &= s >= edge[:, None]
        r, c = np.nonzero(good)
        order = np.lexsort((vid[c], -s[r, c], r))
        r, c = r[order], c[order]
        first = np.searchsorted(r, np.arange(len(qid)))
        keep = np.arange(len(r)) - first[r] < k
        r, c = r[keep], c[keep]
        return pa.RecordBatch.from_arrays([pa.array(qid[r]), pa.array(vid[c]), pa.array(s[r, c])], ["query_id", "vec_id", "score"])

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, queries, rows = None, [], []

        def flush() -> Iterator[pa.RecordBatch]:
            if queries and rows:
                qid, least, q = (np.concatenate(x) for x in zip(*queries, strict=True))
                vid, _, v = (np.concatenate(x) for x in zip(*rows, strict=True))
                for a in range(0, len(qid), max(1, CELLS // len(vid))):
                    b = slice(a, a + max(1, CELLS // len(vid)))
                    yield task(qid[b], least[b], q[b], vid, v)

        for batch in batches:
            block, chunk, ids, least = (batch.column(c).to_numpy(zero_copy_only=False) for c in (0, 1, 3, 4))
            is_row = batch.column(2).to_numpy(zero_copy_only=False).astype(bool)
            v = _matrix(batch.column(5), dims)
            cuts = np.flatnonzero((block[1:] != block[:-1]) | (chunk[1:] != chunk[:-1]) | (is_row[1:] != is_row[:-1])) + 1
            for a, b in zip([0, *cuts], [*cuts, len(block)], strict=True):
                if a == b:
                    continue
                if (block[a], chunk[a]) != key:
                    yield from flush()
                    key, queries, rows = (block[a], chunk[a]), [], []
                (rows if is_row[a] else queries).append((ids[a:b], least[a:b], v[a:b]))
        yield from flush()

    return made


def _scored(asked: DataFrame, index: DataFrame, k: int, dims: int) -> DataFrame:
    """query_id, vec_id, score: the best of each query in each annulus that it asks for. ``asked``: block, id, least, v."""
    n = shuffle_partitions(asked.sparkSession)
    chunks = F.broadcast(asked.groupBy("block").agg(F.ceil(F.count("*") / CHUNK).cast("int").alias("chunks")))  # a row an annulus
    left = asked.join(chunks, "block").select("block", F.pmod(F.xxhash64("id"), "chunks").cast("int").alias("chunk"), F.lit(False).alias("row"), "id", "least", "v")
    right = index.join(chunks, "block").select("block", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.lit(True).alias("row"), "id", F.lit(0).cast("long").alias("least"), "v")
    dealt = left.union(right).repartition(n, "block", "chunk").sortWithinPartitions("block", "chunk", "row")
    return dealt.select("block", "chunk", "row", "id", "least", "v").mapInArrow(_best(k, dims), "query_id long, vec_id long, score long")


def _walk(pivots: np.ndarray, top: float, dims: int, annuli: tuple, begin: int, end: int):
    """Of each query (id, v, kth) the annuli from the ``begin``-th to the ``end``-th nearest that may hold a row at or above its k-th score."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, pivot, lo, hi = annuli
        least = np.iinfo(np.int64).min
        for whole in batches:
            for a in range(0, whole.num_rows, max(1, CELLS // len(block))):
                batch = whole.slice(a, max(1, CELLS // len(block)))
                v = _matrix(batch.column(1), dims).astype(float)
                x = np.hstack([v, np.zeros((len(v), 1))])
                d = _distances(x, pivots)[:, pivot]
                bound = np.maximum(np.maximum(lo - d, d - hi), 0.0)
                kth = batch.column(2).to_numpy(zero_copy_only=False).astype(float)  # NaN: fewer than k seen, no bound
                size = (x * x).sum(1) + top
                radius = np.sqrt(np.maximum(0.0, size - 2 * kth)) + 1e-3 + 1e-6 * np.sqrt(size)
                radius = np.where(np.isnan(radius), np.inf, radius)
                near = np.lexsort((np.broadcast_to(block, bound.shape), bound), axis=1)[:, begin:end]
                r, c = np.nonzero(np.take_along_axis(bound, near, 1) <= radius[:, None])
                known = batch.column(2).fill_null(least).to_numpy(zero_copy_only=False)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(block[near[r, c]]), batch.column(0).take(pa.array(r)), pa.array(known[r]), batch.column(1).take(pa.array(r))], ["block", "id", "least", "v"]
                )

    return made


def search(
    rows: DataFrame, queries: DataFrame, k: int = 20, vec_id: str = "vec_id", vector: str = "embedding", scale: int = 64, pivots: int = PIVOTS, block: int = BLOCK
) -> tuple[DataFrame, dict[str, int]]:
    """(query_id, rank, vec_id, score) of the k rows with other ids of the highest inner product to each query, and what it cost: pairs
    of a query and a row that were scored, and all pairs."""
    spark = rows.sparkSession
    v = whole_numbers(rows, vec_id, vector, scale)
    norm = F.aggregate("v", F.lit(0.0), lambda a, e: a + e.cast("double") * e.cast("double"))
    size = v.agg(F.coalesce(F.max(norm), F.lit(0.0)).alias("top"), F.coalesce(F.max(F.size("v")), F.lit(0)).alias("dims"), F.count("*").alias("n")).first()
    q = whole_numbers(queries, vec_id, vector, scale)
    q = materialize(q.groupBy("id").agg(F.min("v").alias("v")), "queries")
    asked_for = q.agg(F.coalesce(F.max(F.size("v")), F.lit(0)).alias("dims"), F.count("*").alias("n")).first()
    top, dims = float(size["top"]), max(size["dims"], asked_for["dims"])
    cost = {"scored": 0, "pairs": size["n"] * asked_for["n"]}
    # pivots: the ``pivots`` rows of least hashed id, a bounded sample of all rows; every row is indexed
    sample = v.orderBy(F.xxhash64("id"), "id").limit(pivots).toArrow()
    if not sample.num_rows:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long"), cost
    p = _lifted(_matrix(pa.concat_arrays(sample["v"].chunks), dims), top)
    index = in_annuli(keyed_by_pivot(v, p, top, dims), max(block, -(-size["n"] // ANNULI)), "annuli")
    told = index.groupBy("block", "pivot").agg(F.min("far").alias("lo"), F.max("far").alias("hi"), F.count("*").alias("n")).orderBy("block").toArrow()
    annuli = tuple(told[c].to_numpy() for c in ("block", "pivot", "lo", "hi"))
    sizes = F.broadcast(spark.createDataFrame(list(zip(told["block"].to_pylist(), told["n"].to_pylist(), strict=True)), "block long, n long"))

    best = spark.createDataFrame([], "query_id long, vec_id long, score long")
    kth = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    begin, step = 0, 1
    while begin < told.num_rows:
        least = best.groupBy(F.col("query_id").alias("id")).agg(F.min("score").alias("kth"), F.count("*").alias("c")).where(F.col("c") == k)
        reach = q.join(least.select("id", "kth"), "id", "left").select("id", "v", "kth")
        asked = materialize(reach.mapInArrow(_walk(p, top, dims, annuli, begin, begin + step), "block long, id long, least long, v array<long>"), "asked")
        scored = asked.join(sizes, "block").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        if not scored:
            break  # every query's next annulus is beyond its radius, and so are all after it
        cost["scored"] += scored
        found = best.unionByName(_scored(asked, index, k, dims)).withColumn("rank", F.row_number().over(kth)).where(F.col("rank") <= k)
        last, best = best, materialize(found.select("query_id", "vec_id", "score"), "best")
        drop_table(asked)
        if begin:
            drop_table(last)
        begin, step = begin + step, step * FACTOR
    return best.withColumn("rank", F.row_number().over(kth).cast("int")).select("query_id", "rank", "vec_id", "score"), cost


def top_k(rows: DataFrame, queries: DataFrame, k: int = 20, **how) -> DataFrame:
    return search(rows, queries, k, **how)[0]


ORACLE = """
WITH v AS (SELECT vec_id, [floor(64 * x::DOUBLE)::BIGINT for x in embedding] AS v FROM embeddings
           WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_sum([a[1] * a[2] for a in list_zip(q.v, c.v)])::BIGINT AS score
      FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0)
SELECT query_id, rank::INT AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 20
"""
