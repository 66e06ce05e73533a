"""The pipeline's stages against plain versions on a small table."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from layerflow.llm import store

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def table(spark, sf_dir, tmp_path_factory):
    root = tmp_path_factory.mktemp("corpus")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(150)
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    leak = items.orderBy("item_id").first().text
    more = [(9001, "12 34 !!", "en", "s", 8), (9002, None, None, None, None), (9003, f"Before it all {leak} and after it.", "en", "s", 1), (9004, "token = abcdef0123456789", "en", "s", 1), (None, "a text that nobody gave an id to", "en", "s", 1)]
    docs.unionByName(docs.limit(5).withColumn("doc_id", F.col("doc_id") + 5000)).unionByName(spark.createDataFrame(more, SCHEMA)).write.parquet(f"{root}/documents.parquet")
    items.write.parquet(f"{root}/benchmark.parquet")
    return str(root)


def test_stages(spark, table):
    docs = spark.read.parquet(f"{table}/documents.parquet")
    seen = []
    for name, stage in pipeline.STAGES:
        new = store.written(stage(spark, docs, table), "stage")
        seen.append((docs, new))
        docs = new
    ids = lambda d: {r.doc_id for r in d.select("doc_id").collect()}
    (before, kept) = seen[0]
    assert ids(before) - ids(kept) == {9001, 9002} and kept.columns == pipeline.COLUMNS
    (before, kept) = seen[1]
    assert not ids(kept) & {5000 + r.doc_id for r in before.collect() if r.doc_id is not None and r.doc_id < 5000} and None in ids(kept)
    (before, kept) = seen[2]
    assert 9003 in ids(before) and 9003 not in ids(kept)
    (before, kept) = seen[3]
    assert ids(before) == ids(kept) and kept.where("doc_id = 9004").first().text == "[secret]"
    (before, kept) = seen[4]
    assert ids(before) == ids(kept) and {"n_tokens", "ids_sha256", "decoded_sha256"} <= set(kept.columns)


def test_empty(spark, tmp_path, sf_dir):
    spark.createDataFrame([], SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet(f"{sf_dir}/benchmark.parquet").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert pipeline.run(spark, str(tmp_path)).count() == 0


def test_stages_on_nulls_and_repeats(spark, tmp_path, sf_dir):
    """Null and empty texts, null ids and repeated rows, with an empty benchmark."""
    spark.read.parquet(f"{sf_dir}/benchmark.parquet").limit(0).write.parquet(f"{tmp_path}/benchmark.parquet")
    rows = [(1, None, "en", "s", None), (2, "", None, "s", 0), (3, "token = abcdef0123456789", "en", None, 24), (3, "token = abcdef0123456789", "en", None, 24), (None, "plain words here", "en", "s", 16)]
    docs = spark.createDataFrame(rows, SCHEMA)
    at = lambda d, *c: sorted((tuple(r) for r in d.select("doc_id", *c).collect()), key=repr)
    assert at(pipeline.drop_leaks(spark, docs, str(tmp_path))) == sorted([(r[0],) for r in rows], key=repr)
    masked = at(pipeline.mask_secrets(spark, docs, str(tmp_path)), "text")
    assert masked == sorted([(1, None), (2, ""), (3, "[secret]"), (3, "[secret]"), (None, "plain words here")], key=repr)
    tokens = at(pipeline.encode(spark, docs, str(tmp_path)), "n_tokens")
    assert len(tokens) == 5 and (1, 1) in tokens and (2, 1) in tokens
    assert len({n for i, n in tokens if i == 3}) == 1
