"""Rows that decontamination drops when the benchmark comes in blocks."""

import pytest

from cellbalance.llm import fmindex


@pytest.mark.parametrize("block_bytes", [32 << 20, 2000])
def test_each_row_is_judged_by_itself(spark, block_bytes):
    item = lambda k: " ".join(f"b{k}x{i}" for i in range(20))
    bench = spark.createDataFrame([(k, item(k)) for k in range(40)], "item_id long, text string")
    clean = "nothing of the benchmark stands in this row"
    both = f"{item(3)} and then {item(31)}"
    rows = [(None, item(5), "bad"), (None, clean, "good"), (1, item(7), "bad"), (1, clean, "good"), (2, clean, "good"), (2, clean, "good"), (3, both, "bad"), (3, both, "bad"), (4, None, "good"), (5, "", "good")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = fmindex.decontaminated(docs, bench, block_bytes=block_bytes)
    key = lambda r: (r[0] is None, r[0] or 0, r[1] or "")
    assert got.columns == docs.columns
    assert sorted((tuple(r) for r in got.collect()), key=key) == sorted((r for r in rows if r[2] == "good"), key=key)


def test_hits_of_two_blocks_add_up(spark):
    # each item covers 13 words of 400, which is under a twentieth; the two together are over it
    bench = spark.createDataFrame([(k, " ".join(f"b{k}x{i}" for i in range(13))) for k in range(40)], "item_id long, text string")
    rest = " ".join(f"w{i}" for i in range(374))
    parts = [bench.filter(f"item_id = {k}").first().text for k in (3, 31)]
    docs = spark.createDataFrame([(None, f"{parts[0]} {rest} {parts[1]}"), (1, f"{parts[0]} {rest} w0 w1 w2 w3 w4 w5 w6 w7 w8 w9 w10 w11 w12")], "doc_id long, text string")
    assert [r.doc_id for r in fmindex.decontaminated(docs, bench, block_bytes=2000).collect()] == [1]
