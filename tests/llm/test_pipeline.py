"""The corpus pipeline on the smallest tables: each stage against its operator, and on odd rows."""

import hashlib

import corpus_pipeline
from cellbalance.llm import neardup
from cellbalance.llm.common import table


def test_stages_keep_columns_and_drop_what_they_reject(spark, data):
    docs = table(spark, data, "documents")
    extra = spark.createDataFrame([(None, None, None, None, None), (900_001, None, "en", "x", 0), (900_002, "", None, None, 0), (900_003, "12 34", "en", "x", 5)], docs.schema)
    now, counts = docs.union(extra), []
    for name, stage in corpus_pipeline.STAGES:
        after = stage(spark, now, data)
        if name != "tokens":
            assert after.columns == docs.columns
        after.write.mode("overwrite").parquet(path := f"{spark.conf.get('spark.checkpoint.dir')}/test-{name}")
        after = spark.read.parquet(path)
        counts.append(after.count())
        if name == "language":
            assert after.filter("doc_id > 900000 or doc_id is null").count() == 0
        if name == "near_duplicates":
            again = neardup.near_duplicates(after, shingle=5)
            assert again.filter("not kept").count() == 0
        now = after
    assert counts == sorted(counts, reverse=True) and counts[-1] > 0
    for r in now.limit(20).collect():
        assert r.n_tokens * 4 == len(r.ids) and hashlib.sha256(bytes(r.ids)).hexdigest() == r.ids_sha256
    text = {r.doc_id: r.text for r in docs.collect()}
    assert all(hashlib.sha256(text[r.doc_id].encode()).hexdigest() == r.decoded_sha256 for r in now.select("doc_id", "decoded_sha256").collect())


def test_empty_tables(spark, data):
    empty = table(spark, data, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, data).count() == 0
