"""MinHash near-duplicates through a multi-index Hamming join.

Signature: `chunks * width` min-hash symbols of 16 bits. Two documents of similarity J differ in
each symbol with probability about 1 - J. The signature is split into `chunks` pieces; by pigeonhole
any pair within distance chunks * (errors + 1) - 1 has a piece with at most `errors` differing
symbols. For every piece each choice of `errors` symbols to leave out gives one index key, so the
index returns all such pairs, and a pair beyond the distance whenever one piece is close enough. With
the defaults (10 pieces of 6 symbols, one error) a pair of J = 0.8 is missed with probability 2e-5.
Every link is confirmed on the full shingle sets.

Equal sets are one class, a vertex of its own, and stay one row. A bucket first tries only the link of
each member to one member, the one of least document id (a star): copies mostly come after what they copy.
Pairs inside a component need no further test. Pairs of a bucket that
lie in different components are tested one by one in buckets up to `bucket_limit`; members of larger ones
go through an exact prefix-filter join on their rarest shingles, so no bucket is paired out and nothing
is dropped. Joins on a key that many rows share deal the key out over several tasks.

Defined results: null text, empty text or text without words has an empty set, is its own component
and is kept. In near_duplicates rows with a null id keep a null component, and rows that repeat an id are
one document with several sets. In one_of_each a row is known by id and text: rows that share an id but
not a text are judged apart, rows without an id take part, and of equal rows one stays. Only the id and
text columns are read, so other columns may have any name.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import chain, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellbalance.llm.common import LOWER, MEMORIES, Interned, Work, make_room, mix64, runs

_STEP = np.uint64(0x9E3779B97F4A7C15)
_WORDS = MEMORIES.setdefault("neardup", Interned(xxhash.xxh3_64_intdigest))


def shingle_sets(texts: list[bytes | None], k: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of each text."""
    words = [t.translate(LOWER).split() if t else [] for t in texts]
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    flat = np.fromiter(map(_WORDS.__getitem__, chain.from_iterable(words)), np.uint64, int(sizes.sum()))
    rolled = flat[: max(0, len(flat) - k + 1)].copy()
    for j in range(1, k):
        rolled = rolled * _STEP + flat[j : j + len(rolled)]
    rolled = mix64(rolled)
    out, at = [], 0
    for n in sizes:
        if n >= k:
            out.append(np.unique(rolled[at : at + n - k + 1]))
        elif n:
            one = np.full(1, n, np.uint64)
            for w in flat[at : at + n]:
                one = one * _STEP + w
            out.append(mix64(one))
        else:
            out.append(flat[:0])
        at += n
    return out


def _multipliers(n: int) -> np.ndarray:
    return mix64(np.arange(1, n + 1, dtype=np.uint64) * _STEP) | np.uint64(1)


def index_keys(sets: list[np.ndarray], pieces: int, width: int, errors: int) -> np.ndarray:
    """One row of index keys per non-empty set."""
    sets = [s for s in sets if len(s)]
    masks = list(combinations(range(width), width - errors))
    if not sets:
        return np.zeros((0, pieces * len(masks)), np.int64)
    flat = np.concatenate(sets)
    starts = np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    symbols = np.empty((len(sets), pieces * width), np.uint64)
    buffer = np.empty_like(flat)
    for j, m in enumerate(_multipliers(pieces * width)):
        np.multiply(flat, m, out=buffer)
        symbols[:, j] = np.minimum.reduceat(buffer, starts)
    symbols = mix64(symbols) >> np.uint64(48)
    keys = np.empty((len(sets), pieces * len(masks)), np.uint64)
    for i in range(keys.shape[1]):
        p, mask = divmod(i, len(masks))
        key = np.full(len(sets), i + 1, np.uint64)
        for c in masks[mask]:
            key = key * _STEP + symbols[:, p * width + c]
        keys[:, i] = mix64(key)
    return keys.view(np.int64)


def _signed(docs: DataFrame, id_col: str, text_col: str, k: int, pieces: int, width: int, errors: int) -> DataFrame:
    """row (unique), doc_id, h (hash of the text), n (set size), two words that name the set, its index keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room("neardup")
        for batch in batches:
            for a, b, texts in runs(batch.column(1), 1 << 20):
                sets = shingle_sets(texts, k)
                n = np.array([len(s) for s in sets], np.int64)
                name1 = np.array([s.sum(dtype=np.uint64) for s in sets], np.uint64).view(np.int64)
                name2 = np.array([mix64(s ^ _STEP).sum(dtype=np.uint64) for s in sets], np.uint64).view(np.int64)
                keys = index_keys(sets, pieces, width, errors)
                ends = np.concatenate([[0], np.cumsum((n > 0) * keys.shape[1])]).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0)[a:b], batch.column(2)[a:b], pa.array(n), pa.array(name1), pa.array(name2),
                     pa.ListArray.from_arrays(pa.array(ends), pa.array(keys.ravel()))],
                    names=["doc_id", "h", "n", "name1", "name2", "keys"],
                )

    signed = _named(docs, id_col, text_col).mapInArrow(run, "doc_id long, h long, n long, name1 long, name2 long, keys array<long>")
    return signed.withColumn("row", F.monotonically_increasing_id())


def _named(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, text and h, a hash of the text: a row's id and hash tell its text."""
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("h"))


def parted(work: Work, docs: DataFrame, id_col: str, text_col: str, named: DataFrame, most: int = 1 << 27) -> tuple[DataFrame, DataFrame]:
    """(maybe, surely_not): docs parted by a bitmap of the rows that the written table named (doc_id, h) tells.
    All rows named are in the first part, with some others, a sixteenth at the most while `most` bits suffice;
    so a join with named moves these texts and not all of them. The bitmap stays below `most` bits."""
    bits = max(1 << 15, min(most, 1 << (16 * named.count()).bit_length()))
    place = lambda i, h: F.pmod(F.xxhash64(i, h), F.lit(bits)) + 1
    at = place(F.col("doc_id"), F.col("h"))
    maps = work.table(named.select(F.bitmap_bucket_number(at).alias("_bucket"), F.bitmap_bit_position(at).alias("_bit")).groupBy("_bucket").agg(F.bitmap_construct_agg("_bit").alias("_map")), "bitmap")
    own = place(docs[id_col].cast("long"), F.xxhash64(docs[text_col].cast("string")))
    bit = F.bitmap_bit_position(own)
    byte = F.conv(F.hex(F.substring(maps["_map"], (F.shiftright(bit, 3) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    hit = (F.bitmap_bucket_number(own) == maps["_bucket"]) & (F.call_function("getbit", byte, (bit % 8).cast("int")) == 1)
    return docs.join(F.broadcast(maps), hit, "left_semi"), docs.join(F.broadcast(maps), hit, "left_anti")


def _sets(docs: DataFrame, k: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room("neardup")
        for batch in batches:
            for a, b, texts in runs(batch.column(1), 1 << 20):
                sets = [s.view(np.int64) for s in shingle_sets(texts, k)]
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], pa.array(sets, pa.list_(pa.int64()))], names=["cid", "shingles"])

    return docs.mapInArrow(run, "cid long, shingles array<long>")


def components(work: Work, edges: DataFrame) -> DataFrame:
    """(v, comp): the smallest vertex that each vertex of the edges (a, b) reaches.

    Each round takes the least label among neighbours and then the label's own label, so chains
    shrink geometrically; only a count of changes returns to the driver.
    """
    both = work.table(edges.select("a", "b").union(edges.select(F.col("b"), F.col("a"))).distinct(), "edges")
    labels = work.table(
        both.groupBy(F.col("a").alias("v")).agg(F.least(F.min("b"), F.first("a")).alias("comp")).withColumn("moved", F.lit(True)), "labels"
    ).drop("moved")
    while True:
        near = both.join(labels, both.b == labels.v).groupBy(F.col("a").alias("v")).agg(F.min("comp").alias("near"))
        step = labels.join(near, "v").select("v", F.col("comp").alias("old"), F.least("comp", "near").alias("via"))
        jump = labels.select(F.col("v").alias("via"), F.col("comp").alias("far"))
        nxt = work.table(
            step.join(jump, "via").select("v", F.least("via", "far").alias("comp"), (F.least("via", "far") < F.col("old")).alias("moved")), "labels"
        )
        moved = nxt.filter("moved").limit(1).count()
        work.drop(labels)
        labels = nxt.drop("moved")
        if not moved:
            work.drop(both)
            return labels


def _dealt(many: DataFrame, hot: DataFrame, key: str, other: str, one: DataFrame) -> DataFrame:
    """many joined with one (a row per key) on the key; a key of the written table hot (key, last) is dealt
    out by the other end over last + 1 copies of its row, so that no task gets all rows of a hot key."""
    spread = many.join(hot, key, "left").withColumn("_part", F.pmod(F.xxhash64(other), F.coalesce("last", F.lit(0)) + 1).cast("int")).drop("last")
    again = one.join(hot, key, "left").withColumn("_part", F.explode(F.sequence(F.lit(0), F.coalesce("last", F.lit(0))))).drop("last")
    return spread.join(again, [key, "_part"]).drop("_part")


def _similar(work: Work, pairs: DataFrame, sets: DataFrame, percent: int, most: int = 64) -> DataFrame:
    """Those of the written pairs (a, b) whose full sets have 100 * intersection >= percent * union."""
    left = sets.select(F.col("cid").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("cid").alias("b"), F.col("shingles").alias("sb"))
    # keys of more than `most` pairs: few rows, which the planner broadcasts while they are
    hot = [work.table(pairs.groupBy(k).agg(F.expr(f"cast((count(*) - 1) div {most} as int)").alias("last")).filter("last > 0"), "hot-keys") for k in "ab"]
    both = _dealt(_dealt(pairs, hot[0], "a", "b", left), hot[1], "b", "a", right)
    same = both.select("a", "b", F.size("sa").alias("na"), F.size("sb").alias("nb"), F.size(F.array_intersect("sa", "sb")).alias("common"))
    return same.filter(F.expr(f"100 * common >= {percent} * (na + nb - common)")).select("a", "b").distinct()


def _star(buckets: DataFrame) -> DataFrame:
    """(a, b): each member beside the first member b with which it shares most keys."""
    rep = buckets.groupBy("key").agg(F.min(F.struct(F.col("first").isNull(), "first", "cid")).alias("rep"))
    ties = buckets.join(rep, "key").filter("cid <> rep.cid").groupBy(F.col("cid").alias("a"), F.col("rep.cid").alias("b")).agg(F.count("*").alias("votes"))
    return ties.groupBy("a").agg(F.max_by("b", F.struct("votes", -F.col("b"))).alias("b"))


def _labelled(df: DataFrame, comp: DataFrame) -> DataFrame:
    return df.join(comp.withColumnRenamed("v", "cid"), "cid", "left").withColumn("comp", F.coalesce("comp", "cid"))


def _rare_prefix_pairs(work: Work, hot: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Exact candidates among the hot classes (cid, comp): pairs of different components that share
    one of their rarest shingles. A set of n with a partner above the threshold shares one of its
    n - ceil(t * n) + 1 rarest; the positional bound then tests each match."""
    tokens = sets.join(hot, "cid").select("cid", "comp", F.size("shingles").alias("n"), F.explode("shingles").alias("tok"))
    df = tokens.groupBy("tok").agg(F.count("*").alias("df"), F.min("comp").alias("c1"), F.max("comp").alias("c2"))
    held = tokens.join(df, "tok").groupBy("cid", "comp", "n").agg(F.sort_array(F.collect_list(F.struct("df", "tok", "c1", "c2"))).alias("all"))
    prefix = held.select(
        "cid", "comp", "n", F.posexplode(F.slice("all", F.lit(1), F.expr(f"cast(n - ({percent} * n + 99) div 100 + 1 as int)"))).alias("pos", "t")
    ).filter("t.df > 1 and t.c1 < t.c2")
    prefix = work.table(prefix.select("cid", "comp", "n", "pos", F.col("t.tok").alias("tok")), "prefix")
    # sets alike enough differ by one band of sizes at most, so a shingle that many prefixes hold is split by
    # size; the larger set of a pair looks in its own band and in the one below
    prefix = prefix.withColumn("band", F.floor(F.log(F.col("n")) / F.log(F.lit(100.0 / percent)) + 1e-9))
    x, y = (prefix.select("tok", "band", *(F.col(c).alias(f"{c}_{s}") for c in ("cid", "comp", "n", "pos"))) for s in "xy")
    y = y.withColumn("low", F.col("band")).withColumn("band", F.explode(F.array("band", F.col("band") - 1)))
    need = f"cast(({percent} * (n_x + n_y) + {99 + percent}) div {100 + percent} as bigint)"
    return (
        x.join(y, ["tok", "band"])
        .filter("(low > band or cid_x < cid_y) and comp_x <> comp_y")
        .filter(f"100 * least(n_x, n_y) >= {percent} * greatest(n_x, n_y)")
        .filter(f"1 + least(n_x - pos_x - 1, n_y - pos_y - 1) >= {need}")
        .select(F.least("cid_x", "cid_y").alias("a"), F.greatest("cid_x", "cid_y").alias("b"))
        .distinct()
    )


def linked_classes(
    work: Work, docs: DataFrame, id_col: str, text_col: str, shingle: int, percent: int, pieces: int = 10, width: int = 6, errors: int = 1, bucket_limit: int = 24
) -> tuple[DataFrame, DataFrame]:
    """(signed, classes): a row of docs each, and a row (name1, name2, n, cid, comp) for each different set
    that is not empty, where comp is the least cid that cid reaches."""
    signed = work.table(_signed(docs, id_col, text_col, shingle, pieces, width, errors), "signed")
    classes = work.table(signed.filter("n > 0").groupBy("name1", "name2", "n").agg(F.min("row").alias("cid"), F.min("doc_id").alias("first")), "classes")
    # keys move once, with nothing but their class: most of them nobody shares, and those go no further
    firsts = classes.select(F.col("cid").alias("row"))
    entries = signed.join(firsts, "row", "left_semi").select(F.col("row").alias("cid"), F.explode(F.array_distinct("keys")).alias("key"))
    held = F.count("*").over(Window.partitionBy("key"))
    shared = work.table(entries.withColumn("held", held).filter("held > 1"), "shared")
    work.release()
    reps = signed.select(F.col("row").alias("cid"), "doc_id", "h", "n").join(classes.select("cid", "first"), "cid")
    buckets = work.table(shared.join(reps, "cid"), "buckets")
    work.drop(shared)
    named = work.table(buckets.select("cid", F.col("doc_id").alias("id"), F.col("h").alias("hash")).distinct(), "named")
    rows, _ = parted(work, docs, id_col, text_col, named.select(F.col("id").alias("doc_id"), F.col("hash").alias("h")))
    rows = _named(rows, id_col, text_col)
    texts = rows.join(named, rows.doc_id.eqNullSafe(named.id) & (rows.h == named.hash)).select("cid", "text")
    sets = work.table(_sets(texts, shingle).dropDuplicates(["cid"]), "sets")
    work.release()

    star = work.table(_star(buckets), "star")
    comp = components(work, work.table(_similar(work, star, sets, percent), "links"))
    work.release()

    placed = _labelled(buckets.select("key", "cid", "n", "held"), comp)
    open_ = placed.groupBy("key").agg(F.min("comp").alias("c1"), F.max("comp").alias("c2")).filter("c1 < c2").select("key")
    mixed = work.table(placed.join(open_, "key"), "mixed")  # buckets within one component need nothing more
    small = mixed.filter(F.col("held") <= bucket_limit)
    x, y = (small.select("key", *(F.col(c).alias(f"{c}_{s}") for c in ("cid", "comp", "n"))) for s in "xy")
    pairs = (
        x.join(y, "key")
        .filter("cid_x < cid_y and comp_x <> comp_y")
        .filter(f"100 * least(n_x, n_y) >= {percent} * greatest(n_x, n_y)")
        .select(F.col("cid_x").alias("a"), F.col("cid_y").alias("b"))
        .distinct()
    )
    hot = work.table(mixed.filter(F.col("held") > bucket_limit).select("cid", "comp").distinct(), "hot")
    pairs = work.table(pairs.union(_rare_prefix_pairs(work, hot, sets, percent)).distinct(), "pairs")
    more = _similar(work, pairs, sets, percent)
    across = _labelled(_labelled(more.withColumnRenamed("a", "cid"), comp).select(F.col("comp").alias("a"), F.col("b").alias("cid")), comp)
    joined = components(work, work.table(across.select("a", F.col("comp").alias("b")).filter("a <> b").distinct(), "links"))
    final = (
        _labelled(classes, comp)
        .join(joined.select(F.col("v").alias("comp"), F.col("comp").alias("last")), "comp", "left")
        .select("name1", "name2", "n", "cid", F.coalesce("last", "comp").alias("comp"))
    )
    return signed, work.table(final, "final")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, percent: int = 80, **how) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of docs."""
    work = Work(docs.sparkSession)
    signed, classes = linked_classes(work, docs.filter(F.col(id_col).isNotNull()), id_col, text_col, shingle, percent, **how)
    least = signed.filter("n > 0").groupBy("name1", "name2", "n").agg(F.min("doc_id").alias("least"))
    firsts = least.join(classes, ["name1", "name2", "n"])
    roots = firsts.groupBy("comp").agg(F.min("least").alias("component_id"))
    firsts = firsts.join(roots, "comp").select("name1", "name2", "n", "component_id")
    rows = signed.join(firsts, ["name1", "name2", "n"], "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))
    rows = work.table(rows, "rows")
    # a document of several sets ties their components together
    several = rows.groupBy("doc_id").agg(F.min("component_id").alias("a"), F.max("component_id").alias("z")).filter("a < z").select("doc_id", "a")
    ties = work.table(rows.join(several, "doc_id").filter("a < component_id").select("a", F.col("component_id").alias("b")).distinct(), "ties")
    if not ties.isEmpty():
        tied = components(work, ties).select(F.col("v").alias("component_id"), F.col("comp").alias("least"))
        rows = rows.join(tied, "component_id", "left").withColumn("component_id", F.coalesce("least", "component_id"))
    bare = _signed(docs.filter(F.col(id_col).isNull()), id_col, text_col, shingle, 1, 1, 0)
    bare = bare.select("doc_id", F.col("n").alias("n_shingles"), F.lit(None).cast("long").alias("component_id"), F.lit(True).alias("kept"))
    out = rows.select("doc_id", "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"))
    return work.table(out.union(bare), "result")


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, percent: int = 80, **how) -> DataFrame:
    """One row of each near-duplicate group, with all its columns: the one of least id, then least hash."""
    work = Work(docs.sparkSession)
    signed, classes = linked_classes(work, docs, id_col, text_col, shingle, percent, **how)
    rows = signed.filter("n > 0").groupBy("name1", "name2", "n", "doc_id", "h").agg(F.count("*").alias("copies"))
    rows = work.table(rows.join(classes, ["name1", "name2", "n"]).select("doc_id", "h", "copies", "comp"), "rows")
    # two steps on longs, which hash aggregation takes: the least id, then the least hash among its texts
    ids = rows.groupBy(F.col("comp").alias("c")).agg(F.min("doc_id").alias("root_id"))
    hashes = rows.join(ids, (rows.comp == ids.c) & rows.doc_id.eqNullSafe(ids.root_id)).groupBy("c", "root_id").agg(F.min("h").alias("hash"))
    chosen = work.table(hashes, "chosen")
    flagged = rows.join(chosen, rows.comp == chosen.c).withColumn("stays", rows.doc_id.eqNullSafe(F.col("root_id")) & (F.col("h") == F.col("hash")))
    gone = work.table(flagged.filter("not stays").select("doc_id", "h"), "gone")
    again = work.table(flagged.filter("stays and copies > 1").select("doc_id", "h"), "again")
    work.release()

    def of(rows: DataFrame, named: DataFrame):
        return rows[id_col].cast("long").eqNullSafe(named.doc_id) & (F.xxhash64(rows[text_col].cast("string")) == named.h)

    maybe, left = parted(work, docs, id_col, text_col, gone)
    left = left.union(maybe.join(gone, of(maybe, gone), "left_anti"))
    if again.isEmpty():
        return left
    maybe, left = parted(work, left, id_col, text_col, again)
    repeated = maybe.join(again, of(maybe, again))
    columns = [maybe[c] for c in docs.columns]
    one = repeated.groupBy(again.doc_id, again.h).agg(F.min_by(F.struct(columns), F.xxhash64(*columns)).alias("_one")).select("_one.*")
    return left.union(maybe.join(again, of(maybe, again), "left_anti")).union(one)
