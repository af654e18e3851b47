"""The registered queries of the training-data operators, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from privgrove.llm import audio, bm25, bpe_count, jaccard, langid, licenses, mixing, packing, planes, warc


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_bm25_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return bm25.search(docs, docs.where("doc_id % 100 = 0"), k=10)


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"), 2048, 0)


def op3_telephony_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return audio.media_features(table(spark, sf_dir, "documents"))


def op4_raked_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = mixing.sampled(table(spark, sf_dir, "documents"))
    return kept.selectExpr("doc_id", "mix.source", "mix.lang", "mix.topic", "mix.tokens AS n_tokens", "mix.probability")


def op5_bit_plane_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return planes.token_files(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"), 2)


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scanned(table(spark, sf_dir, "documents")).drop("spans")


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_count.token_counts(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"), 4096)


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.near_duplicates(table(spark, sf_dir, "documents"), words=3, percent=90)


def op6_warc_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archived(table(spark, sf_dir, "pages"))


def op7_crf_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.languages(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_bm25_search": op1_bm25_search,
    "op2_best_fit_packing": op2_best_fit_packing,
    "op3_telephony_audio": op3_telephony_audio,
    "op4_raked_mixing": op4_raked_mixing,
    "op5_bit_plane_ids": op5_bit_plane_ids,
    "op6_warc_chain": op6_warc_chain,
    "op7_crf_language": op7_crf_language,
    "op8_license_scan": op8_license_scan,
    "op9_token_counts": op9_token_counts,
    "op10_jaccard_join": op10_jaccard_join,
}

SQL: dict[str, str] = {
    "op1_bm25_search": bm25.search_sql(),
    "op4_raked_mixing": mixing.sample_sql(),
    "op8_license_scan": licenses.scan_sql(),
}
