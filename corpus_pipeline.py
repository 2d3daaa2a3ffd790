"""A corpus from raw documents: junk out, near-copies out, personal data masked, sources mixed, texts encoded.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before it kept. All but the last return the
columns of documents. run() writes every stage as Parquet in the shared folder and rereads it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boolmat.llm import bpe, minhash, mixing, pii, quality_rules
from boolmat.llm.common import files_for, load, written


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that neither the base rule nor the learned decision list rejects."""
    rules = quality_rules.learn_rules(docs, load(spark, sf_dir, "labels"))
    rows = docs.select("text", F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    return quality_rules.apply_rules(rows, rules).where("kept").select("row.*")


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group whose five-word shingles agree by 0.8 or more: the one with the smallest id.

    Every row is a document of its own: of rows with equal ids or without an id, copies go too. Ids come before null.
    """
    rows = written(docs.withColumn("__row", F.monotonically_increasing_id()), "near-rows")  # stored, so that the keys stay
    groups = minhash.near_duplicates(rows.select(F.col("__row").alias("doc_id"), "text"), size=5, percent=80)
    placed = written(groups.select(F.col("doc_id").alias("__row"), "component_id").join(rows.select("__row", "doc_id"), "__row"), "near-placed", files_for(spark, rows.count()))
    first = placed.groupBy("component_id").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "__row"))["__row"].alias("__row"))
    return rows.join(first.select("__row"), "__row", "left_semi").select(docs.columns)


def pii_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with personal data in their texts replaced by its kind."""
    return pii.redact(docs, pii.fit(docs))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it, so that sources meet their target sizes."""
    return mixing.mixed_documents(docs)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256, ids) of every row: the token ids to train on, and their digests."""
    import public_tokenizers

    vocabulary = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
    return bpe.digests(bpe.encode(docs, *vocabulary), *vocabulary, with_ids=True)


STAGES = [("quality_rules", quality_stage), ("minhash_near_dedup", near_duplicate_stage), ("pii", pii_stage), ("mixing", mixing_stage), ("byte_bpe", encoding_stage)]

#: Learned rules, banding, span models and rounding have no SQL twin.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
