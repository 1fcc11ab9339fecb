"""The rebalancing sink where its join is a merge join and some partitions of the state hold no cell."""

import pytest

from cellbalance import registry
from cellbalance.streaming import rebalance


@pytest.fixture
def many_partitions(spark):
    held = {k: spark.conf.get(k, None) for k in ("spark.sql.shuffle.partitions", "spark.sql.autoBroadcastJoinThreshold")}
    spark.conf.set("spark.sql.shuffle.partitions", "100")  # the hash of none of the 512 cells falls into partition 65
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield
    for k, v in held.items():
        spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def test_assignment_where_partitions_hold_no_cell(spark, data, many_partitions):
    found = registry.QUERIES["streamed_assignment"](spark, data).toPandas()
    events = spark.read.parquet(f"{data}/events.parquet").withColumn("ts", rebalance.F.col("ts").cast("timestamp"))
    want = {(r.cx, r.cy, r.cz): r["count"] for r in rebalance.cells(events).groupBy("cx", "cy", "cz").count().collect()}
    assert len(found) == 512 and set(found.rank_id) <= set(range(16))
    assert {(r.cx, r.cy, r.cz): r.weight for r in found.itertuples() if r.weight} == want


def test_log_of_a_stream_where_partitions_hold_no_cell(spark, data, tmp_path, many_partitions):
    log = rebalance.rebalanced_stream(spark, f"{data}/events.parquet*", f"file://{tmp_path}/one", 16, 1.5, "hilbert").collect()
    assert [(r.batch, r.rebalanced) for r in log] == [(0, True)]
    assert log[0].mean_load * 16 == spark.read.parquet(f"{data}/events.parquet").count()
