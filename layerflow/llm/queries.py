"""The queries of this subpackage: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from layerflow.llm import ann, decontaminate, extract, fingerprints, jaccard, licenses, pieces, ppm, secrets, suffixes


def tokenizer_path() -> str:
    """Where the installed public piece model lies; it isn't part of this repository."""
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return secrets.scan_secrets(docs).drop("text", "n_secrets")


def op2_repeated_word_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return fingerprints.remove_repeats(docs).drop("text")


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", licenses.document_path().alias("path"), "text")
    return licenses.scan_licenses(docs)


def op4_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return decontaminate.decontaminate(docs, _table(spark, sf_dir, "benchmark")).drop("text", "items")


def op5_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return extract.extract(pages, extract.learn_costs(pages)).drop("html")


def op6_repeated_byte_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return suffixes.remove_repeats(docs).drop("text")


def op7_shingle_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return jaccard.link_components(docs).select("doc_id", "n_shingles", "component_id", "set_id")


def op8_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return pieces.encode_decode(docs, tokenizer_path()).drop("text")


def op9_nearest_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = _table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return ann.nearest(vectors, vectors.where("vec_id % 20 = 0"))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return ppm.identify(docs).select("doc_id", "held_out", "lang_pred", "score", "bits_per_byte")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_secret_scan": op1_secret_scan,
    "op2_repeated_word_windows": op2_repeated_word_windows,
    "op3_license_scan": op3_license_scan,
    "op4_benchmark_decontamination": op4_benchmark_decontamination,
    "op5_main_text": op5_main_text,
    "op6_repeated_byte_strings": op6_repeated_byte_strings,
    "op7_shingle_links": op7_shingle_links,
    "op8_piece_codec": op8_piece_codec,
    "op9_nearest_vectors": op9_nearest_vectors,
    "op10_language_id": op10_language_id,
}

ORACLES: dict[str, str] = {"op3_license_scan": licenses.oracle()}
