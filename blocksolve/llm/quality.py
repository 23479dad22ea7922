"""Quality rules with risk-controlled thresholds. Only DataFrame functions.

Each rule rejects a document whose measure exceeds a cutoff. All rules start off and come down a ladder that is fixed before any
label is read: step 3 i + j lowers rule j to the i-th cutoff of the grid (the grid descends). A step is one hypothesis about all rules
together: "they reject more than ``alpha`` of the good documents that the base rule passes". It is refuted, so the step is certified, if a
binomial with rate ``alpha`` would show no more false rejections than the labelled good documents do with probability
``delta`` / strata at most (the exact tail). Steps are tested in order up to the first that fails (fixed-sequence testing, so the length of the ladder costs
nothing), and the division by the number of strata corrects for the families. With probability 1 - ``delta``, in all strata at once, the rules together
reject at most a share ``alpha`` of the good documents that pass the base rule. The base rule itself is given, not chosen, and stands outside this bound.

Nothing but the step is chosen on labels: neither the measures nor the ladder are fitted, so every labelled document serves as holdout.
A stratum is a source that has labelled good documents enough to certify a step at all (without a false rejection); the sources with fewer
form one stratum together. That choice looks at their numbers only, never at measures. Sources without any labelled good
document, and strata in which no step is certified, have their rules off.

Words are ``[^\\x20\\x09-\\x0D]+``. Defined results: a null text has no words and fails the base
rule; a null source is a source of its own; labels are reduced to one row per doc_id by their
largest value, null labels are no labels; repeated documents count each.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksolve.llm.common import materialize

GRID = tuple(round(0.95 - 0.05 * i, 2) for i in range(19)) + (0.03, 0.02, 0.01)
RULES = ("symbol_share", "dup_line_share", "repeat_share")


def measures(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", stratum: str = "source") -> DataFrame:
    """doc_id, stratum, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words of every whole text."""
    base = docs.select(F.col(doc_id).alias("doc_id"), F.col(stratum).cast("string").alias("stratum"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    words = base.select("doc_id", "stratum", "text", F.expr(r"array_remove(split(text, '[\\x20\\x09-\\x0D]+'), '')").alias("w"))
    counted = words.select(
        "doc_id", "stratum",
        F.size("w").alias("n_words"),
        F.length(F.array_join("w", "")).alias("word_chars"),
        F.expr("length(text) - length(translate(text, '#*$%&|<>', ''))").alias("n_symbols"),
        F.expr(r"filter(split(text, '\n'), x -> x rlike '[^\\x20\\x09-\\x0D]')").alias("lines"),
        F.expr("CASE WHEN size(w) > 3 THEN transform(sequence(0, size(w) - 3), i -> xxhash64(w[i], w[i + 1], w[i + 2])) END").alias("win"),
    )
    places = counted.select(
        "doc_id", "stratum", "n_words", "word_chars", "n_symbols",
        F.size("lines").alias("n_lines"),
        F.expr("size(lines) - size(array_distinct(lines))").alias("n_dup_lines"),
        F.expr("CASE WHEN size(win) > size(array_distinct(win)) THEN array_sort(transform(win, (h, i) -> struct(h AS h, i AS i))) END").alias("s"),
    )
    again = places.withColumn(
        "p", F.expr("CASE WHEN s IS NOT NULL THEN sort_array(transform(filter(s, (x, i) -> x.h = get(s, i - 1).h OR x.h = get(s, i + 1).h), x -> x.i)) END")
    ).drop("s")
    covered = F.expr("CASE WHEN p IS NULL THEN 0 ELSE aggregate(p, named_struct('n', 0, 'end', 0), (a, x) -> named_struct('n', a.n + x + 3 - greatest(a.end, x), 'end', x + 3), a -> a.n) END")
    longs = ["n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines"]
    return again.select("doc_id", "stratum", *[F.col(c).cast("long").alias(c) for c in longs], covered.cast("long").alias("n_repeat_words"))


def shares(m: DataFrame) -> DataFrame:
    """Adds the rules' measures, each from 0 to 1."""
    part = lambda a, b: F.least(F.lit(1.0), F.col(a) / F.greatest(F.col(b), F.lit(1)))
    return m.withColumns({
        "symbol_share": part("n_symbols", "word_chars"),
        "dup_line_share": part("n_dup_lines", "n_lines"),
        "repeat_share": part("n_repeat_words", "n_words"),
    })


def base_failed():
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def strata_of(held: DataFrame, alpha: float, delta: float) -> DataFrame:
    """stratum, pooled: each source with labelled good documents, and whether it has too few for itself."""
    per = held.groupBy("stratum").agg(F.count("*").alias("n"))
    least = per.agg((F.log(F.lit(delta) / (F.count("*") + 1)) / F.log(F.lit(1 - alpha))).alias("least"))
    return per.crossJoin(F.broadcast(least)).select("stratum", (F.col("n") < F.col("least")).alias("pooled"))


def thresholds(measured: DataFrame, labels: DataFrame, alpha: float = 0.02, delta: float = 0.05, grid: tuple[float, ...] = GRID, rules: tuple[str, ...] = RULES) -> DataFrame:
    """stratum, pooled, n, strata, step, rejected and cut_<rule> (null: off) of every source with labelled good documents."""
    good = labels.groupBy("doc_id").agg(F.max("quality").alias("q")).where("q = 1 AND doc_id IS NOT NULL").select("doc_id")
    held = measured.join(good, "doc_id", "left_semi").where(~base_failed())
    ladder, wide = F.array(*[F.lit(float(c)) for c in sorted(grid, reverse=True)]), len(rules)
    # the step from which on some rule rejects the document; beyond the last step: none ever does
    passes = lambda r: F.size(F.filter(ladder, lambda c: c >= F.col(r)))
    fails = F.least(*[F.when(passes(r) < len(grid), passes(r) * wide + j).otherwise(len(grid) * wide) for j, r in enumerate(rules)])
    counted = held.select("stratum", fails.alias("fails")).groupBy("stratum", "fails").agg(F.count("*").alias("c"))
    place = materialize(strata_of(held, alpha, delta), "strata")  # a row a source
    own = F.when(~F.col("pooled"), F.col("stratum"))
    told = counted.join(place.withColumnRenamed("stratum", "s"), F.col("stratum").eqNullSafe(F.col("s"))).groupBy(own.alias("family"), "pooled", "fails").agg(F.sum("c").alias("c"))
    families = told.groupBy("family", "pooled").agg(F.sum("c").alias("n"), F.map_from_entries(F.collect_list(F.struct("fails", "c"))).alias("by"))
    strata = families.agg(F.count("*").alias("strata"))
    steps = families.crossJoin(F.broadcast(strata)).select("*", F.explode(F.sequence(F.lit(0), F.lit(len(grid) * wide - 1))).alias("step"))
    tested = steps.withColumn("k", F.expr("aggregate(map_entries(by), 0L, (a, e) -> a + IF(e.key <= step, e.value, 0L))"))
    tested = tested.withColumn("sure", log_binomial_cdf("k", "n", alpha) <= F.log(F.lit(delta) / F.col("strata")))
    run = Window.partitionBy("family", "pooled").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    best = tested.withColumn("all_sure", F.min("sure").over(run)).where("all_sure").groupBy("family", "pooled").agg(F.max_by(F.struct("n", "strata", "step", F.col("k").alias("rejected")), "step").alias("b"))
    lowered = lambda j: F.floor((F.col("b.step") - j) / wide).cast("int")
    cuts = [F.when(lowered(j) >= 0, F.get(ladder, lowered(j))).alias(f"cut_{r}") for j, r in enumerate(rules)]
    best = best.select("family", F.col("pooled").alias("of_pool"), "b.*", *cuts)
    return place.join(best, (F.col("pooled") == F.col("of_pool")) & own.eqNullSafe(F.col("family"))).drop("family", "of_pool")


def log_binomial_cdf(k: str, n: str, p: float):
    """ln P(Binomial(n, p) <= k), by summing its terms in logarithms; 0 where k is above the mean (it can't be small there)."""
    return F.expr(f"""CASE WHEN {k} > {n} * {p!r}D THEN 0D ELSE
      aggregate(sequence(0L, {k}), named_struct('t', {n} * ln(1 - {p!r}D), 's', {n} * ln(1 - {p!r}D)),
        (a, i) -> CASE WHEN i = 0 THEN a ELSE named_struct(
          't', a.t + ln(({n} - i + 1) / i) + ln({p!r}D / (1 - {p!r}D)),
          's', greatest(a.s, a.t + ln(({n} - i + 1) / i) + ln({p!r}D / (1 - {p!r}D)))
               + log1p(exp(-abs(a.s - (a.t + ln(({n} - i + 1) / i) + ln({p!r}D / (1 - {p!r}D))))))) END,
        a -> a.s) END""")


def judge(docs: DataFrame, labels: DataFrame, **risk) -> DataFrame:
    """Per document: the counts, base_failed, kept, and the rules that rejected it.

    The counts are written once to the shared folder, as the thresholds need those of labelled
    documents before any document can be judged.
    """
    measured = shares(materialize(measures(docs), "quality"))
    cut = thresholds(measured, labels, **risk).select(F.col("stratum").alias("cut_stratum"), *[f"cut_{r}" for r in RULES])
    joined = measured.join(cut, measured["stratum"].eqNullSafe(cut["cut_stratum"]), "left")
    hits = F.array_compact(F.array(*[F.when(F.col(r) > F.col(f"cut_{r}"), F.lit(r)) for r in RULES]))
    return joined.select(
        "doc_id", "stratum", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base_failed().alias("base_failed"), hits.alias("rejected_by")
    ).withColumn("kept", ~F.col("base_failed") & (F.size("rejected_by") == 0))


ORACLE = r"""
WITH d AS (SELECT doc_id, source, coalesce(text, '') AS text,
                  list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
pos AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS i FROM d),
tri AS (SELECT doc_id, i, word || ' ' || lead(word) OVER o || ' ' || lead(word, 2) OVER o AS t FROM pos WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
many AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, t) AS c FROM tri WHERE t IS NOT NULL) WHERE c > 1),
covered AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM many, range(0, 3) r(j) GROUP BY doc_id),
ln AS (SELECT doc_id, count(*) AS n, count(*) - count(DISTINCT line) AS dup
       FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id),
m AS (SELECT d.doc_id, d.source, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
             (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
             coalesce(ln.n, 0)::BIGINT AS n_lines, coalesce(ln.dup, 0)::BIGINT AS n_dup_lines, coalesce(covered.n, 0)::BIGINT AS n_repeat_words
      FROM d LEFT JOIN ln USING (doc_id) LEFT JOIN covered USING (doc_id)),
r AS (SELECT *, least(1.0, n_symbols / greatest(word_chars, 1)) AS a, least(1.0, n_dup_lines / greatest(n_lines, 1)) AS b,
             least(1.0, n_repeat_words / greatest(n_words, 1)) AS c FROM m),
f AS (SELECT *, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS failed FROM r),
g AS (SELECT row_number() OVER (ORDER BY c DESC) - 1 AS i, c FROM (SELECT unnest([""" + ", ".join(f"{c!r}::DOUBLE" for c in GRID) + r"""]) AS c)),
ladder AS (SELECT i * 3 + j AS step, c, j FROM g, range(0, 3) q(j)),
settings AS (SELECT s.step, min(l.c) FILTER (WHERE l.j = 0) AS ca, min(l.c) FILTER (WHERE l.j = 1) AS cb, min(l.c) FILTER (WHERE l.j = 2) AS cc
             FROM ladder s JOIN ladder l ON l.step <= s.step GROUP BY s.step),
held AS (SELECT source, a, b, c FROM f SEMI JOIN (SELECT doc_id FROM labels GROUP BY doc_id HAVING max(quality) = 1) USING (doc_id) WHERE NOT failed),
sizes AS (SELECT source, count(*) AS n FROM held GROUP BY source),
place AS (SELECT source, n < ln(0.05 / ((SELECT count(*) FROM sizes) + 1)) / ln(0.98) AS pooled FROM sizes),
fam AS (SELECT pooled, CASE WHEN NOT pooled THEN held.source END AS family, a, b, c FROM held JOIN place ON held.source IS NOT DISTINCT FROM place.source),
t AS (SELECT family, pooled, step, count(*) AS n, count(*) FILTER (WHERE a > ca OR coalesce(b > cb, false) OR coalesce(c > cc, false)) AS k FROM fam, settings GROUP BY ALL),
u AS (SELECT *, CASE WHEN k > n * 0.02 THEN 1.0 ELSE (SELECT sum(exp(lgamma(t.n + 1) - lgamma(i + 1) - lgamma(t.n - i + 1) + i * ln(0.02) + (t.n - i) * ln(0.98))) FROM range(0, t.k + 1) q(i)) END
             <= 0.05 / (SELECT count(DISTINCT (family, pooled)) FROM fam) AS sure FROM t),
best AS (SELECT family, pooled, max(step) AS step FROM (SELECT *, bool_and(sure) OVER (PARTITION BY family, pooled ORDER BY step) AS all_sure FROM u) WHERE all_sure GROUP BY 1, 2),
cut AS (SELECT source, ca, cb, cc FROM place JOIN best ON best.pooled = place.pooled AND best.family IS NOT DISTINCT FROM CASE WHEN NOT place.pooled THEN source END JOIN settings USING (step))
SELECT f.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, failed AS base_failed,
       NOT failed AND NOT coalesce(a > ca, false) AND NOT coalesce(b > cb, false) AND NOT coalesce(c > cc, false) AS kept
FROM f LEFT JOIN cut ON f.source IS NOT DISTINCT FROM cut.source
"""
