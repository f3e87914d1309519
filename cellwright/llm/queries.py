"""The thin queries of the training-data operators, their production parameters and, where SQL can express them, their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import read_table


def _byte_bpe() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN


def crc_column(c: str):
    return F.crc32(F.col(c))


def op1_additive_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .additive_ann import search

    return search(read_table(spark, sf_dir, "embeddings"), k=20)


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .exact_dedup import exact_groups

    return exact_groups(read_table(spark, sf_dir, "documents"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import near_groups

    return near_groups(read_table(spark, sf_dir, "documents"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_counts import token_counts

    return token_counts(read_table(spark, sf_dir, "documents"), *_byte_bpe())


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import fit, score

    docs, labels = read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels")
    held_out = (F.crc32(F.col("doc_id").cast("string")) % 5) == 0
    scored = score(docs, fit(docs, labels))
    return scored.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op6_bpe_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .chunk_bpe import encode_decode

    out = encode_decode(read_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
    return out.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_files import read_token_files, write_token_files

    folder, id_of = write_token_files(read_table(spark, sf_dir, "documents"), *_byte_bpe())
    return read_token_files(spark, folder, id_of).select("doc_id", "start", "n_tokens", crc_column("ids").alias("ids_crc32"))


def op8_slot_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import shard

    out, slot_map = shard(read_table(spark, sf_dir, "documents"), 16)
    slot_map.save(spark)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op9_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_dedup import remove_repeats

    out = remove_repeats(read_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack

    return pack(read_table(spark, sf_dir, "documents"), *_byte_bpe())


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_additive_ann, op2_exact_dedup, op3_simhash, op4_token_counts, op5_toxicity, op6_bpe_roundtrip, op7_token_files, op8_slot_sharding, op9_suffix_dedup, op10_packing, pipeline)
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    space = r"regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')"
    return {
        "op1_additive_ann": """
            WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings
                WHERE len(list_filter(embedding, lambda y: y IS NULL OR NOT isfinite(y))) = 0 AND len(list_filter(embedding, lambda y: y <> 0)) > 0),
            s AS (SELECT q.vec_id AS query_id, e.vec_id AS vec_id, list_inner_product(e.x, q.x) AS score FROM v q JOIN v e ON q.vec_id % 20 = 0 AND e.vec_id <> q.vec_id)
            SELECT query_id, CAST(rank AS INT) AS rank, vec_id, score
            FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 20""",
        "op2_exact_dedup": f"""
            SELECT doc_id, min(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size,
                   doc_id = min(doc_id) OVER g AS kept, sha256(norm) AS text_sha256
            FROM (SELECT doc_id, {space} AS norm FROM documents) WINDOW g AS (PARTITION BY norm)""",
        # every 100-byte window by its digest: all but the first of equal ones are repeats; their covers are joined into spans
        "op9_suffix_dedup": """
            WITH d AS (SELECT doc_id, encode(coalesce(text, '')) AS b, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
            w AS (SELECT doc_id, i, md5_number(hex(array_slice(b, i + 1, i + 100))) AS h FROM (SELECT doc_id, b, unnest(range(0, n - 99)) AS i FROM d WHERE n >= 100)),
            r AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY h ORDER BY doc_id, i) AS k FROM w) WHERE k > 1),
            p AS (SELECT doc_id, i, lag(i + 100) OVER (PARTITION BY doc_id ORDER BY i) AS before FROM r),
            g AS (SELECT doc_id, i, sum(CASE WHEN i <= before THEN 0 ELSE 1 END) OVER (PARTITION BY doc_id ORDER BY i) AS span FROM p),
            s AS (SELECT doc_id, span, min(i) AS a, max(i) + 100 AS e FROM g GROUP BY doc_id, span),
            x AS (SELECT doc_id, list(a ORDER BY a) AS a, list(e ORDER BY a) AS e, sum(e - a) AS removed, count(*) AS spans FROM s GROUP BY doc_id),
            parts AS (SELECT doc_id, n, b, removed, spans, list_transform(range(1, spans + 2), lambda j:
                hex(array_slice(b, (CASE WHEN j = 1 THEN 0 ELSE e[j - 1] END) + 1, CASE WHEN j > spans THEN n ELSE a[j] END))) AS kept FROM d LEFT JOIN x USING (doc_id))
            SELECT doc_id, n AS n_bytes, CAST(coalesce(removed, 0) AS BIGINT) AS n_removed, coalesce(spans, 0) AS n_spans,
                sha256(CASE WHEN spans IS NULL THEN b ELSE unhex(array_to_string(kept, '')) END) AS kept_sha256 FROM parts""",
    }
