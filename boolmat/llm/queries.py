"""The ten operators and the pipeline applied to whole tables, with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bpe, chat_format, minhash, mixing, pii, quality_model, quality_rules, suffix_dedup, warc
from .common import load, written


def op1_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = r"\### Assistant: </turn> ok"
    extra = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id bigint, turn bigint, role string, text string")
    turns = load(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(extra)
    return chat_format.conversation_digests(chat_format.format_conversations(turns))


def op2_weakly_supervised_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return pii.find_spans(docs, pii.fit(docs))


def op3_collision_counting_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = load(spark, sf_dir, "embeddings")
    return ann.nearest(vectors, vectors.where("vec_id % 20 = 0"), k=20)


def op4_decision_list_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    rules = quality_rules.learn_rules(docs, load(spark, sf_dir, "labels"))
    return quality_rules.apply_rules(docs, rules).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op5_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(load(spark, sf_dir, "documents"), length=400)


def op6_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = warc.write_archives(load(spark, sf_dir, "pages"))
    return warc.page_captures(warc.assemble(warc.read_records(spark, path, with_payload=False)))


def _vocabulary() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(bpe.encode(load(spark, sf_dir, "documents"), *_vocabulary()), *_vocabulary())


def op8_minhash_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(load(spark, sf_dir, "documents"), size=3, percent=85)


def held_out() -> Column:
    """A fifth of the ids; a row without an id is not held out."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def op9_pairwise_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = load(spark, sf_dir, "documents").select("doc_id", "text"), load(spark, sf_dir, "labels")
    held = held_out()
    rows = written(quality_model.measured(docs), "measured")  # learned from and scored
    model = quality_model.fit(rows, labels.where(~held))
    scored = quality_model.score(rows, model)
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= model.place).cast("int").alias("predicted"))


def op10_pivotal_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(load(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def pii_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op2 gives without its learned part."""
    return pii.find_spans(load(spark, sf_dir, "documents"), None).select("doc_id", "n_email", "n_ip", "n_card", "n_phone")


def base_text_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op4 gives without its learned part."""
    judged = quality_rules.apply_rules(load(spark, sf_dir, "documents").select("doc_id", "text"), quality_rules.DecisionList(()))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


def quality_hold_out(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which documents op9 learns nothing from."""
    return load(spark, sf_dir, "documents").select("doc_id", held_out().alias("held_out"))


def mixing_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op10 gives without its random part."""
    return mixing.mix(load(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", F.round("target", 6).alias("target"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [op1_chat_formatting, op2_weakly_supervised_pii, op3_collision_counting_neighbours, op4_decision_list_rules, op5_suffix_array_dedup, op6_warc_transactions, op7_byte_bpe, op8_minhash_near_duplicates, op9_pairwise_quality, op10_pivotal_mixing, pipeline, pii_base_counts, base_text_statistics, quality_hold_out, mixing_targets]
    return {f.__name__: f for f in found}
