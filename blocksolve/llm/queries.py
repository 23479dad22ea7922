"""One query per operator: op<N>_<name>, with production parameters over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksolve.llm import chat, langid, mixing, nearest, neardup, ppm, quality, sentencepieces, substrings, warc
from blocksolve.llm.common import read


def piece_model() -> str:
    """The public vocabulary that the queries use; the operator takes any file."""
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    back = sentencepieces.decode(sentencepieces.encode(docs, piece_model()), piece_model())
    return back.select("doc_id", F.size("ids").alias("n_ids"), "ids", F.col("decoded").eqNullSafe(F.col("text")).alias("round_trip"))


def op2_chat_snapshots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.collapse_and_render(read(spark, sf_dir, "conversations"))


def op3_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.join(read(spark, sf_dir, "documents")).select("doc_id", "class_id", "copy_of", "n_links")


def op4_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    archives = warc.write_archives(warc.plan_revisits(read(spark, sf_dir, "pages")))
    return warc.read_archives(archives, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op5_poisson_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read(spark, sf_dir, "documents"))


def op6_debruijn_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.cut(read(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_words", "n_removed", "kept_sha256")


def op7_pivot_annuli(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "embeddings")
    return nearest.top_k(rows, rows.where(F.col("vec_id") % 20 == 0))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def remainder(doc_id: str, n: int):
    """crc32 of the id as text, modulo n (a null id counts as the empty text)."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit(""))) % n


def op9_language_bitmask(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    held = remainder("doc_id", 3) == 1
    model = langid.train(docs.where(~held))
    return langid.predict(docs, model, ["doc_id"]).select("doc_id", held.alias("held_out"), "lang_pred", "score")


def op10_ppm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    held = remainder("doc_id", 7) == 2
    model = ppm.train(docs.where(~held))
    return ppm.score(docs, model, ["doc_id"]).select(
        "doc_id", held.alias("held_out"), "n_tokens", "n_known", F.lit(model.tokens).cast("long").alias("train_tokens"), "base_score", "score"
    )


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_sentencepiece, op2_chat_snapshots, op3_ngram_jaccard, op4_warc_round_trip, op5_poisson_mixing, op6_debruijn_substrings, op7_pivot_annuli, op8_quality_rules, op9_language_bitmask, op10_ppm_scores)}


def oracle_sql() -> dict[str, str]:
    return {"op2_chat_snapshots": chat.ORACLE, "op3_ngram_jaccard": neardup.ORACLE, "op4_warc_round_trip": warc.ORACLE, "op5_poisson_mixing": mixing.ORACLE, "op6_debruijn_substrings": substrings.ORACLE, "op7_pivot_annuli": nearest.ORACLE, "op8_quality_rules": quality.ORACLE}
