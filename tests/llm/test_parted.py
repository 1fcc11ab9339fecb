"""Texts that a small table of ids and hashes names are told from the others before any text moves."""

from cellbalance.llm import neardup
from cellbalance.llm.common import Work
from pyspark.sql import functions as F


def test_named_rows_are_in_the_first_part_and_few_others(spark):
    texts = spark.range(20_000).selectExpr("nullif(id, 7) as doc_id", "case when id % 5000 <> 3 then concat('text ', id) end as text", "id as `a.b`", "id as _map")
    named = texts.filter("`a.b` % 100 in (3, 7)").select("doc_id", F.xxhash64("text").alias("h"))
    work = Work(spark)
    for most in (1 << 27, 1 << 15):
        maybe, rest = neardup.parted(work, texts, "doc_id", "text", work.table(named, "named"), most)
        assert maybe.columns == rest.columns == texts.columns
        held, others = ({r["a.b"] for r in part.collect()} for part in (maybe, rest))
        assert not held & others and held | others == set(range(20_000))
        assert {i for i in range(20_000) if i % 100 in (3, 7)} <= held and len(held) < 400 + 20_000 // 16 + 200
    maybe, rest = neardup.parted(work, texts, "doc_id", "text", work.table(named.limit(0), "named"))
    assert maybe.isEmpty() and rest.count() == 20_000

