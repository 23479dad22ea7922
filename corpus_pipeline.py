"""A training corpus from raw documents: five stages, each over all rows that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksolve.llm import langid, mixing, neardup, sentencepieces, substrings
from blocksolve.llm.common import drop_table, materialize, read
from blocksolve.llm.queries import piece_model

#: a document whose best language explains less than this share of its n-grams is rejected
LEAST_LANGUAGE_SCORE = 0.2


def _columns(made: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of ``docs``. An extra column named like one that a stage works with may be missing from then on; those of documents never are."""
    return made.select([F.col(f"`{c}`") for c in docs.columns if c in made.columns])


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects texts without a letter and texts that no learned language explains. A missing language is filled in.

    A lettered text too short for an n-gram is no evidence against any language: it stays.
    """
    names = [c for c in docs.columns if c.lower() not in ("lang_pred", "score")]
    told = langid.predict(docs, langid.train(docs), names)
    kept = told.where((F.col("lang_pred") != langid.UNKNOWN) & ((F.col("score") >= LEAST_LANGUAGE_SCORE) | (F.octet_length("text") < langid.N)))
    return kept.withColumn("lang", F.coalesce("lang", "lang_pred")).select(names)


def ngram_jaccard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies stays, that of the least doc_id."""
    return neardup.dedup(docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words in repeated windows leave the texts; documents stay."""
    cut = substrings.cut(docs).withColumns({"text": F.col("kept"), "n_chars": F.length("kept").cast("long")})
    return _columns(cut, docs)


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeat, or leave, so that sources reach their target shares; rows are shuffled."""
    return _columns(mixing.mix(docs), docs)


def sentencepiece(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, source, lang, n_ids and ids of every row."""
    return sentencepieces.encode(docs, piece_model()).select("doc_id", "source", "lang", F.size("ids").alias("n_ids"), "ids")


STAGES = [
    ("language_id", language_id),
    ("ngram_jaccard", ngram_jaccard),
    ("substring_dedup", substring_dedup),
    ("source_mixing", source_mixing),
    ("sentencepiece", sentencepiece),
]

#: models and sketches are not expressible in SQL; tests compare run() with plain Python
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows. A stage's table is deleted once the next one is written; the last stays, as the result reads it."""
    docs, last = read(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
        if last is not None:
            drop_table(last)
        last = docs
    return STAGES[-1][1](spark, docs, sf_dir)
