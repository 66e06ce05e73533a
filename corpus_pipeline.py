"""Corpus pipeline over ``documents``: each stage applies one operator to all that the stage before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from layerflow.llm import decontaminate, jaccard, pieces, ppm, repeats, secrets, store
from layerflow.llm.queries import tokenizer_path

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Above this code length under the best language a text is taken for noise: a plain byte costs 8 bits, running text 2 to 4.
MAX_BITS_PER_BYTE = 8.5
MASK = "[secret]"


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a letter (null and empty texts too) and those that no language's model codes better than noise.

    Repeated rows get one verdict, null ids and languages are no reason to go; an empty table gives an empty one.
    """
    found = ppm.identify(docs)
    return found.where((F.col("lang_pred") != ppm.UNDETERMINED) & (F.coalesce(F.col("bits_per_byte"), F.lit(0.0)) <= MAX_BITS_PER_BYTE)).select(COLUMNS)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents that link, by whatever chain, to each other one stays: that with the smallest id.

    Documents without words link with nothing and stay.  Rows equal in id and text count once.  Null ids come last.
    """
    row = ["_id", "_d1", "_d2"]
    d1, d2 = repeats.digest()
    named = docs.select("*", F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("_id"), d1.alias("_d1"), d2.alias("_d2"))
    found = store.written(jaccard.link_components(named.select("doc_id", "text", *row)), "links")
    first = found.where("component is not null").groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", *row)).alias("k"))
    kept = first.select("k._id", "k._d1", "k._d2").union(found.where("component is null").select(row)).distinct()
    return named.join(kept.hint("shuffle_hash"), row, "left_semi").dropDuplicates(row).select(COLUMNS)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a window of a benchmark item.

    Null and empty texts hold none and stay, as do all documents if the benchmark is empty; repeated rows share their fate.
    """
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return decontaminate.decontaminate(docs, items).where(~F.col("contaminated")).select(COLUMNS)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces every found secret by a mark; keeps all documents, repeated rows and null texts included."""
    found = secrets.scan_secrets(docs, redact=MASK)
    return found.select("doc_id", F.col("redacted").alias("text"), "lang", "source", F.length("redacted").cast("long").alias("n_chars"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, with digests of ids and of the decoded text; one row a row, a null text is an empty one."""
    return pieces.encode_decode(docs, tokenizer_path(), with_ids=True).drop("decoded")


STAGES = [
    ("language ID", language_id),
    ("n-gram Jaccard join", one_of_each_group),
    ("benchmark decontamination", drop_leaks),
    ("secret scans", mask_secrets),
    ("SentencePiece encoding and decoding", encode),
]

#: The stages' results can't be expressed in SQL; tests hold them against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = store.written(stage(spark, docs, sf_dir), name.replace(" ", "_"))
    return STAGES[-1][1](spark, docs, sf_dir)
