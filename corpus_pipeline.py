"""A corpus pipeline of five stages, each over what its predecessor kept; see STAGES."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellwright.llm.common import new_path, read_table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents whose toxicity score is below 0.5. The model learns from the labelled rows of the documents table.

    Null and empty texts are scored as one unknown word; rows are judged singly, so repeated ids, null ids and ties need no
    rule; without usable labels all stay; an empty table gives an empty one."""
    from cellwright.llm.toxicity import fit, score

    model = fit(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
    return score(docs, model, keep=True).where(F.col("__cw_score") < 0.5).select(*docs.columns)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the row with the smallest doc_id of each group of equal texts. A row is known by its doc_id and its text's digest,
    so rows without an id, or of one id with different texts, are judged each. Null and empty texts are one group; of rows
    that share the id that stays, and in groups without any id, all stay; an empty table gives an empty one."""
    from cellwright.llm.exact_dedup import exact_groups, normalised

    gone = exact_groups(docs).where("NOT kept").select(F.col("doc_id").alias("__cw_id"), F.col("text_sha256").alias("__cw_gone")).distinct()
    own = docs.withColumn("__cw_sha", F.sha2(normalised(F.coalesce(docs["text"], F.lit(""))), 256))
    same = own["doc_id"].eqNullSafe(gone["__cw_id"]) & (own["__cw_sha"] == gone["__cw_gone"])
    return own.join(gone, same, "left_anti").select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest doc_id of each near-duplicate group. A row is known by its doc_id and a hash of its
    text, so rows of one id with different texts are judged each; rows without an id go if their group has one with, else
    stay. Texts without words are one group; an empty table gives an empty one."""
    from cellwright.llm.simhash import near_groups

    gone = near_groups(docs).where("NOT doc_id <=> component_id").select(F.col("doc_id").alias("__cw_id"), F.col("text_hash").alias("__cw_gone")).distinct()
    own = docs.withColumn("__cw_hash", F.xxhash64(F.coalesce(docs["text"], F.lit(""))))
    same = own["doc_id"].eqNullSafe(gone["__cw_id"]) & (own["__cw_hash"] == gone["__cw_gone"])
    return own.join(gone, same, "left_anti").select(*docs.columns)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes every byte of a 100-byte string that also starts earlier; n_chars follows. A character that is cut in two goes.

    No row goes, also where nothing is left of its text; null and short texts stay as they are; rows without an id come last,
    those of one id in the order of their blocks; an empty table gives an empty one."""
    from cellwright.llm.suffix_dedup import remove_repeats

    own = {"text": F.col("__cw_text"), "n_chars": F.length("__cw_text").cast("long")}
    kept = remove_repeats(docs, keep=True)
    return kept.select(*(F.when(F.col("__cw_removed") > 0, own[c]).otherwise(F.col(c)).alias(c) if c in own else F.col(c) for c in docs.columns))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs all documents into sequences of at most 1024 tokens; see packing.pack for nulls, ties and empty tables."""
    import public_tokenizers

    from cellwright.llm.packing import pack

    return pack(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [("toxicity", drop_toxic), ("exact_dedup", drop_exact_copies), ("simhash", drop_near_copies), ("suffix_dedup", cut_repeats), ("packing", pack_sequences)]

#: learned scores and suffix runs have no SQL; tests/llm holds the stages against brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """STAGES over documents, each stage's rows written to the shared folder and read again for the next."""
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = new_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
