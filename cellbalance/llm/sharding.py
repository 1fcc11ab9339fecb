"""Sharding by histogram sort, in DataFrame functions only.

Rows are ordered by a non-negative 63-bit key. Each round counts exact bytes and rows between
candidate key boundaries in all partitions at once; bins that hold a splitter further than the
tolerance, or more than their share of bytes, are cut into 256 finer candidates and only their rows
are counted again. When every splitter is within tolerance, rows look up their bin and move once.
Offsets of bins give each row its slot, so no shard is ever gathered by one task.

The driver holds bins, not rows: at most 2048 at first and 256 for each bin cut, and a bin is cut only
if it has over 1/(32 * shards) of all bytes, a splitter, or over `most_rows` rows, so the tasks that number
rows grow with the table. Keys that many rows share are safe as long
as the key ends in bits that tell rows apart; `text_order` puts equal texts next to each other and
spreads them by a hash of the id. Rows that are equal in id and text stay in one bin.

Defined results: a null text has no bytes and checksum 0; a null id sorts by its own hash; an empty
table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellbalance.llm.common import Work

KEY_BITS, FIRST_BITS, NEXT_BITS = 63, 11, 8


def text_order(id_col: str = "doc_id", crc_col: str = "text_crc32") -> Column:
    return F.shiftleft(F.col(crc_col), 31).bitwiseOR(F.xxhash64(id_col).bitwiseAND(F.lit((1 << 31) - 1)))


def _bounded(spark: SparkSession, rows: list[dict], schema: str) -> DataFrame:
    """A small driver-made table as one literal."""
    return spark.range(1).select(F.inline(F.from_json(F.lit(json.dumps(rows)), f"array<struct<{schema}>>")))


def _bin_at(shift: int) -> Column:
    return F.shiftright(F.col("key"), shift)


def histogram(keys: DataFrame, shards: int, tolerance: float, share: int, most_rows: int = 1 << 20) -> list[dict]:
    """Leaf bins (bin, shift, bytes, rows) in key order."""
    spark, shift, leaves = keys.sparkSession, KEY_BITS - FIRST_BITS, []
    total = keys.agg(F.sum("size")).first()[0] or 0
    fresh = [r.asDict() | {"shift": shift} for r in keys.groupBy(_bin_at(shift).alias("bin")).agg(F.sum("size").alias("bytes"), F.count("*").alias("rows")).collect()]
    while True:
        leaves = sorted([*leaves, *fresh], key=lambda b: b["bin"] << b["shift"])
        before, cut = 0, []
        for b in leaves:
            first, last = before * shards // max(total, 1), (before + b["bytes"]) * shards // max(total, 1)
            before += b["bytes"]
            wide = b["rows"] > most_rows or b["bytes"] * shards * share > total or first < last and b["bytes"] > tolerance * total / shards
            if b["shift"] == shift and shift > 0 and b["rows"] > 1 and wide:
                cut.append(b)
        if not cut:
            return leaves
        finer = max(0, shift - NEXT_BITS)
        open_ = _bounded(spark, [{"was": b["bin"]} for b in cut], "was bigint")
        fresh = [
            r.asDict() | {"shift": finer}
            for r in keys.withColumn("was", _bin_at(shift)).join(F.broadcast(open_), "was").groupBy(_bin_at(finer).alias("bin"))
            .agg(F.sum("size").alias("bytes"), F.count("*").alias("rows")).collect()
        ]
        gone = {id(b) for b in cut}
        leaves, shift = [b for b in leaves if id(b) not in gone], finer


def histogram_shards(
    df: DataFrame, key: Column, size: Column, shards: int = 16, tolerance: float = 0.001, share: int = 32, most_rows: int = 1 << 20, work: Work | None = None, ties: tuple[str, ...] = ()
) -> DataFrame:
    """df with shard (0 to shards - 1, near equal bytes, contiguous in key order) and slot."""
    spark = df.sparkSession
    keyed = df.withColumn("key", key).withColumn("size", size)
    counted = (work or Work(spark)).table(keyed.select("key", "size"), "keys")
    leaves = histogram(counted, shards, tolerance, share, most_rows)
    total, before, rows_in, placed = sum(b["bytes"] for b in leaves), 0, [0] * shards, {}
    for b in leaves:
        shard = min(shards - 1, (2 * before + b["bytes"]) * shards // max(1, 2 * total))
        placed.setdefault(b["shift"], []).append({"bin": b["bin"], "to": shard, "skip": rows_in[shard]})
        before += b["bytes"]
        rows_in[shard] += b["rows"]
    found = []
    for shift, rows in placed.items():
        bins = _bounded(spark, rows, "bin bigint, to int, skip bigint").select(F.col("bin").alias(f"b{shift}"), F.struct(F.lit(shift).alias("shift"), "bin", "to", "skip").alias(f"f{shift}"))
        keyed = keyed.withColumn(f"b{shift}", _bin_at(shift)).join(F.broadcast(bins), f"b{shift}", "left").drop(f"b{shift}")
        found.append(f"f{shift}")
    if not found:
        return keyed.withColumn("shard", F.lit(0)).withColumn("slot", F.lit(0).cast("long")).drop("key")
    # a coarser bin that was cut has no entry, so one level matches
    place = keyed.withColumn("place", F.coalesce(*found)).drop(*found)
    inside = Window.partitionBy("place.shift", "place.bin").orderBy("key", *ties)
    return place.withColumn("slot", F.col("place.skip") + F.row_number().over(inside) - 1).withColumn("shard", F.col("place.to")).drop("place", "key")


def document_shards(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shards: int = 16) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot of every document; the text is read once."""
    work = Work(docs.sparkSession)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    narrow = work.table(
        docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32")), "narrow"
    )
    return histogram_shards(narrow, text_order(), F.col("size"), shards, work=work, ties=("doc_id",)).select("doc_id", "size", "text_crc32", "shard", "slot")
