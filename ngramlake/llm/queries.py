"""The registered queries of this folder: thin forms that fix the contract's columns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .common import read


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack_documents

    common.ship(spark)
    return pack_documents(read(spark, sf_dir, "documents"), vocabulary())


def op2_collision_counting(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .vector_search import nearest

    common.ship(spark)
    return nearest(read(spark, sf_dir, "embeddings"))


def op3_suffix_merge_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_dedup import cut_repeats

    common.ship(spark)
    return cut_repeats(read(spark, sf_dir, "documents"), keep_text=False)


def op4_hyperdimensional_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language_id import identify

    common.ship(spark)
    return identify(read(spark, sf_dir, "documents"))


def op5_host_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .url_filter import judge

    common.ship(spark)
    return judge(read(spark, sf_dir, "pages"), read(spark, sf_dir, "labels"))


def op8_wav_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .media import media_columns

    common.ship(spark)
    m = media_columns(read(spark, sf_dir, "documents"), "doc_id", "text", keep_media=False)
    feature = F.concat_ws(":", F.size("pairs").cast("string"), "pairs_sha256")
    return m.select(F.col("id").alias("doc_id"), "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", feature.alias("feature"))


def op9_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import plan

    return plan(read(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op6_attention_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .lm_scoring import score_documents

    common.ship(spark)
    return score_documents(read(spark, sf_dir, "documents"), vocabulary())


def op7_pigeonring_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .near_dedup import near_duplicates

    common.ship(spark)
    return near_duplicates(read(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id", "group_size")


def op10_edit_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .line_dedup import dedup_lines

    common.ship(spark)
    kept = dedup_lines(read(spark, sf_dir, "documents").select("doc_id", "text"), exact=1)
    return kept.select("doc_id", "n_lines", "n_removed", F.octet_length("text").cast("long").alias("n_bytes_kept"), F.sha2("text", 256).alias("kept_sha256"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_harmonic_packing, op2_collision_counting, op3_suffix_merge_dedup, op4_hyperdimensional_language, op5_host_reputation, op8_wav_fingerprints, op9_source_mix,
        op6_attention_scores, op7_pigeonring_simhash, op10_edit_line_dedup,
    )
}


def oracle_sql() -> dict[str, str]:
    from .url_filter import judge_sql

    return {"op5_host_reputation": judge_sql()}
