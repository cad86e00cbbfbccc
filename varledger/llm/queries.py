"""The ten contract queries, each a thin layer over its operator, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _vocab(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack_documents

    return pack_documents(_table(spark, sf_dir, "documents"), tokenizer=_vocab("byte_bpe_50k.json"))


def substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring_dedup import remove_repeats

    kept = remove_repeats(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("row.doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


def quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import judge

    return judge(_table(spark, sf_dir, "documents").select("doc_id", "text")).select(
        "row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def top_k_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .topk import top_k

    vectors = _table(spark, sf_dir, "embeddings")
    return top_k(vectors, vectors.where("vec_id % 50 = 0"))


def jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .jaccard_join import jaccard_components

    return jaccard_components(_table(spark, sf_dir, "documents"))


def language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language_id import fit, held_out, identify

    docs = _table(spark, sf_dir, "documents")
    rows = docs.select("doc_id", "text").withColumn("held_out", held_out())
    return identify(rows, fit(docs)).select("row.doc_id", "row.held_out", "lang_pred", "score")


def token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_counts import count_tokens

    return count_tokens(_table(spark, sf_dir, "documents"), tokenizer=_vocab("word_bpe_49k.json"))


def token_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_archive import archive_documents

    return archive_documents(_table(spark, sf_dir, "documents"), tokenizer=_vocab("byte_bpe_50k.json"))


def piece_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pieces import encode_pieces

    return encode_pieces(_table(spark, sf_dir, "documents"), model_path=_vocab("piece_bpe_32k.model"))


def warc_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import archive_pages

    return archive_pages(_table(spark, sf_dir, "pages"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_substring_dedup": substring_dedup,
        "op2_quality_rules": quality_rules,
        "op3_top_k_search": top_k_search,
        "op4_jaccard_join": jaccard_join,
        "op5_language_id": language_id,
        "op6_token_counts": token_counts,
        "op7_packing": packing,
        "op8_token_archive": token_archive,
        "op9_piece_encoding": piece_encoding,
        "op10_warc_pages": warc_pages,
    }


def oracle_sql() -> dict[str, str]:
    from .oracles import SQL

    return dict(SQL)
