"""Mixing sources to target weights by Poisson replication. Only DataFrame functions.

A source's target repetition rate is its target share of all characters over its present share.
Each document draws how often it appears from a Poisson law with that rate, by inverting the
distribution at a uniform number that its id and the seed fix (a retried task draws the same). A
rate above ``STEP`` is drawn as a sum of independent parts, which has the same law, so a table of
at most ``TERMS`` cumulative probabilities serves every rate. Copies are exploded and dealt out in
the order of a hash of id and copy: a global shuffle of the corpus.

Defined results: a null source is a source of its own; a null or empty text has no characters, so
it counts nothing towards shares but is drawn like any other; a source without characters has
rate 1; a null doc_id draws by the empty id; repeated rows draw alike. Extra columns pass through,
but one named like a result or a helper (copy_no, rate, parts, cdf) is replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blocksolve.llm.common import materialize, shuffle_partitions, uniform, without_columns

STEP = 8.0
TERMS = 64  # P(Poisson(8) > 64) < 1e-32, below one step of the uniform


def rates(docs: DataFrame, weights: dict[str, float] | None = None, temperature: float = 0.7, source: str = "source", text: str = "text") -> DataFrame:
    """source, rate. Shares follow ``weights`` (absent sources: 0), or characters to the power ``temperature``."""
    size = docs.groupBy(source).agg(F.sum(F.coalesce(F.length(text), F.lit(0))).cast("double").alias("chars"))
    if weights is None:
        want = size.withColumn("share", F.pow("chars", F.lit(float(temperature))))
    else:
        table = F.create_map(*[F.lit(x) for kv in weights.items() for x in (kv[0], float(kv[1]))])
        want = size.withColumn("share", F.coalesce(F.try_element_at(table, F.col(source)), F.lit(0.0)))
    total = want.agg(F.sum("chars").alias("all_chars"), F.sum("share").alias("all_share"))  # one row
    rate = F.when((F.col("chars") > 0) & (F.col("all_share") > 0), F.col("share") / F.col("all_share") * F.col("all_chars") / F.col("chars"))
    return want.crossJoin(F.broadcast(total)).select(source, F.coalesce(rate, F.lit(1.0)).alias("rate"))


def with_cdf(rate: DataFrame) -> DataFrame:
    """Adds parts (how many draws are summed) and cdf (cumulative probabilities of one part)."""
    one = rate.withColumn("parts", F.greatest(F.ceil(F.col("rate") / STEP), F.lit(1)).cast("int")).withColumn("mean", F.col("rate") / F.col("parts"))
    grow = F.aggregate(
        F.sequence(F.lit(1), F.lit(TERMS)),
        F.struct(F.exp(-F.col("mean")).alias("p"), F.array(F.exp(-F.col("mean"))).alias("cdf")),
        lambda acc, k: F.struct(
            (acc["p"] * F.col("mean") / k).alias("p"),
            F.concat(acc["cdf"], F.array(F.element_at(acc["cdf"], -1) + acc["p"] * F.col("mean") / k)).alias("cdf"),
        ),
        lambda acc: acc["cdf"],
    )
    return one.select(*rate.columns, "parts", grow.alias("cdf"))


def copies(parts: Column, cdf: Column, doc_id: Column, seed: int) -> Column:
    """How often a document appears: the sum over its parts of the inverse distribution at its uniforms."""
    key = F.coalesce(doc_id.cast("string"), F.lit(""))
    return F.aggregate(
        F.sequence(F.lit(1), parts),
        F.lit(0),
        lambda acc, j: acc + F.size(F.filter(cdf, lambda c: c < uniform(F.lit(seed), key, j))),
    )


def mix(docs: DataFrame, weights: dict[str, float] | None = None, temperature: float = 0.7, seed: int = 17, doc_id: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """The rows of ``docs``, each as often as drawn, with ``copy_no`` from 1, dealt out in hashed order."""
    docs = without_columns(docs, "copy_no", "__mix_source", "__mix_copies", "__mix_place", "rate", "parts", "cdf")
    names = docs.columns
    # written, so that its size is known before the join is planned: Spark broadcasts it only below its limit
    law = materialize(with_cdf(rates(docs.select(source, text), weights, temperature, source, text)).withColumnRenamed(source, "__mix_source"), "rates")
    n = shuffle_partitions(docs.sparkSession)
    drawn = docs.join(law, docs[source].eqNullSafe(law["__mix_source"]), "left").withColumn(
        "__mix_copies", copies(F.coalesce("parts", F.lit(1)), F.col("cdf"), docs[doc_id], seed)
    )
    dealt = drawn.where("__mix_copies > 0").select(
        *[docs[c] for c in names], F.explode(F.sequence(F.lit(1), F.col("__mix_copies"))).alias("copy_no")
    )
    place = F.xxhash64(F.lit(seed), F.col(doc_id), F.col(text), F.col("copy_no"))  # the text too: ids may repeat or be null
    return (
        dealt.withColumn("__mix_place", place).repartition(n, "__mix_place").sortWithinPartitions("__mix_place").drop("__mix_place")
    )


ORACLE = """
WITH size AS (SELECT source, sum(length(coalesce(text, '')))::DOUBLE AS chars FROM documents GROUP BY source),
want AS (SELECT source, chars, pow(chars, 0.7) AS share FROM size),
rate AS (SELECT source, coalesce(CASE WHEN chars > 0 THEN share / (SELECT sum(share) FROM want) * (SELECT sum(chars) FROM want) / chars END, 1.0) AS rate FROM want),
part AS (SELECT source, greatest(ceil(rate / 8.0), 1)::INT AS parts, rate / greatest(ceil(rate / 8.0), 1) AS mean FROM rate),
cdf AS (SELECT source, parts, k, sum(exp(-mean + k * ln(mean) - lgamma(k + 1))) OVER (PARTITION BY source ORDER BY k) AS c
        FROM part, range(0, 65) r(k)),
draw AS (SELECT d.doc_id, d.source, j.j,
           (('0x' || substr(md5('17|' || coalesce(d.doc_id::VARCHAR, '') || '|' || j.j), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0 AS u
         FROM documents d JOIN part p ON d.source IS NOT DISTINCT FROM p.source, range(1, p.parts + 1) j(j)),
n AS (SELECT w.doc_id, count(c.c) AS copies FROM draw w LEFT JOIN cdf c ON w.source IS NOT DISTINCT FROM c.source AND c.c < w.u GROUP BY w.doc_id)
SELECT d.doc_id, d.text, d.lang, d.source, d.n_chars, r.i::INT AS copy_no
FROM documents d JOIN n USING (doc_id), range(1, n.copies + 1) r(i)
"""
