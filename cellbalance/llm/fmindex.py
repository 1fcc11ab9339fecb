"""Benchmark decontamination with an FM-index per training shard.

A shard is a run of whole documents of about `shard_bytes` bytes within one task; a longer text is cut into
pieces that overlap by a window less one word. Its words become symbols of the benchmark's alphabet; runs
of words that no benchmark item holds become one separator, which no window contains. The shard's suffixes
are sorted by prefix doubling, the Burrows-Wheeler sequence goes into a wavelet matrix, every window is
found by backward search over its ranks, and the rows found are located by walking back to sampled suffix
positions. Occurrences are merged into spans.

The benchmark is dealt into blocks of about `block_bytes`, whose windows are built by tasks and sent out
block by block: the driver and each worker hold one block at a time. One pass over the documents looks
for the blocks of `pass_bytes` of benchmark text, which bounds what executors store; a larger benchmark takes
further passes, each over the written table of the one before, which carries the spans found so far. Every
row is judged by itself, so the number of blocks and passes changes no result.

Windows: `window` consecutive words of an item; a shorter item that is not empty is one window.
Defined results: null or empty texts have no words, no spans and no items; items with null or empty
text have no window; an item with a null id is named by the empty string; rows that repeat an id or have
none each get their own result. Other columns are passed on as they are.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StringType, StructField, StructType

from cellbalance.llm.common import ALNUM, Work, make_room, runs

_SPAN = StructType([StructField("start", LongType()), StructField("end", LongType())])
_FOUND = StructType([StructField("n_words", LongType()), StructField("spans", ArrayType(_SPAN)), StructField("items", ArrayType(StringType()))])
_SPANS = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))


class WaveletMatrix:
    """Ranks of symbols in a sequence, by one bit vector per bit of the alphabet."""

    def __init__(self, symbols: np.ndarray, bits: int):
        self.levels = []
        first = np.zeros(1 << bits, np.int64)
        names = np.arange(1 << bits)
        for level in range(bits - 1, -1, -1):
            bit = (symbols >> level) & 1 == 1
            packed = np.packbits(bit, bitorder="little")
            words = np.zeros(len(bit) // 64 + 1, np.uint64)
            words.view(np.uint8)[: len(packed)] = packed
            before = np.concatenate([[0], np.cumsum(np.bitwise_count(words), dtype=np.int64)])
            zeros = int(len(bit) - before[-1])
            self.levels.append((level, words, before, zeros))
            symbols = np.concatenate([symbols[~bit], symbols[bit]])
            first = self._down(self.levels[-1], names, first)
        self.first = first

    @staticmethod
    def _down(held: tuple, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        level, words, before, zeros = held
        word = at >> 6
        ones = before[word] + np.bitwise_count(words[word] & ((np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)))
        return np.where((symbol >> level) & 1 == 1, zeros + ones, at - ones)

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often symbol[i] stands before position at[i]."""
        for held in self.levels:
            at = self._down(held, symbol, at)
        return at - self.first[symbol]


def suffix_order(text: np.ndarray, bits: int) -> np.ndarray:
    """Positions by suffix. Symbol 0 separates: each occurrence is a symbol of its own, ordered by
    position; the text ends with one."""
    n, wide = len(text), max(1, 62 // bits)
    if not n:
        return np.zeros(0, np.int64)
    key, open_, padded = np.zeros(n, np.int64), np.ones(n, bool), np.concatenate([text, np.zeros(wide, text.dtype)])
    for j in range(wide):
        here = padded[j : j + n]
        key = (key << bits) | np.where(open_, here, 0)
        open_ &= here > 0
    order = np.argsort(key, kind="stable")
    sorted_key = key[order]
    head = np.concatenate([[True], sorted_key[1:] != sorted_key[:-1]]) | ~open_[order]
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    del key, sorted_key, padded
    tail = np.concatenate([head[1:], [True]])
    active, h = order[~(head & tail)], wide
    while len(active):
        old, ahead = rank[active], rank[active + h]
        by = np.lexsort((ahead, old))
        active, old, ahead = active[by], old[by], ahead[by]
        at = np.arange(len(active))
        group = np.concatenate([[True], old[1:] != old[:-1]])
        fresh = group | np.concatenate([[True], ahead[1:] != ahead[:-1]])
        starts = np.maximum.accumulate(np.where(fresh, at, 0))
        rank[active] = old + starts - np.maximum.accumulate(np.where(group, at, 0))
        last = np.concatenate([fresh[1:], [True]])
        active, h = active[~(fresh & last)], 2 * h
    order = np.empty(n, np.int64)
    order[rank] = np.arange(n)
    return order


class FMIndex:
    def __init__(self, text: np.ndarray, bits: int, sample: int = 16):
        order = suffix_order(text, bits)
        previous = np.concatenate([text[-1:], text[:-1]])
        self.bwt = previous[order]
        self.tree = WaveletMatrix(self.bwt, bits)
        self.before = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=1 << bits))])
        # a walk never crosses a separator: the first word of each run is sampled as well
        held = (order % sample == 0) | (self.bwt == 0)
        self.held, self.nth, self.at = held, np.cumsum(held) - 1, order[held]

    def back(self, symbol: np.ndarray, row: np.ndarray) -> np.ndarray:
        return self.before[symbol] + self.tree.rank(symbol, row)

    def search(self, patterns: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pattern, low row, high row) of the patterns that occur; pattern i is patterns[i, :sizes[i]]."""
        live = np.arange(len(sizes))
        low, high = np.zeros(len(sizes), np.int64), np.full(len(sizes), len(self.bwt), np.int64)
        for step in range(1, int(sizes.max(initial=0)) + 1):
            more = sizes[live] >= step
            move = live[more]
            symbol = patterns[move, sizes[move] - step]
            low[move], high[move] = self.back(symbol, low[move]), self.back(symbol, high[move])
            live = live[low[live] < high[live]]
        return live, low[live], high[live]

    def locate(self, rows: np.ndarray) -> np.ndarray:
        out, todo, steps = np.empty(len(rows), np.int64), np.arange(len(rows)), 0
        rows = rows.copy()
        while len(todo):
            done = self.held[rows]
            out[todo[done]] = self.at[self.nth[rows[done]]] + steps
            todo, rows = todo[~done], rows[~done]
            rows = self.back(self.bwt[rows], rows)
            steps += 1
        return out


class Phrases:
    """The windows of a block of benchmark items, over the block's own alphabet: distinct windows as rows
    of one matrix, filled up with zeros, and the items that own each."""

    def __init__(self, items: list[tuple[str | None, str | None]], window: int):
        self.ids: dict[bytes, int] = {}
        self.names = sorted({name or "" for name, _ in items})
        nth, rows, owners = {x: i for i, x in enumerate(self.names)}, [], []
        for name, text in items:
            ws = (text or "").encode().translate(ALNUM).split()
            symbols = np.fromiter((self.ids.setdefault(w, len(self.ids) + 1) for w in ws), np.int32, len(ws))
            if len(ws):
                symbols = np.pad(symbols, (0, max(0, window - len(ws))))
                rows.append(np.lib.stride_tricks.sliding_window_view(symbols, window))
                owners.append(np.full(len(rows[-1]), nth[name or ""], np.int64))
        every = np.concatenate(rows) if rows else np.zeros((0, window), np.int32)
        self.rows, which = np.unique(every, axis=0, return_inverse=True)
        self.sizes = (self.rows > 0).sum(1)
        self.bits = max(1, len(self.ids).bit_length())
        owned = np.unique(which.ravel() * max(1, len(self.names)) + (np.concatenate(owners) if owners else np.zeros(0, np.int64)))
        self.owners = owned % max(1, len(self.names))
        self.owned = np.searchsorted(owned // max(1, len(self.names)), np.arange(len(self.rows) + 1))

    def symbols(self, words: list[bytes]) -> np.ndarray:
        get = self.ids.get
        return np.fromiter((get(w, 0) for w in words), np.int32, len(words))


def _ranges(low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All integers of the ranges, and which range each is of."""
    size = high - low
    of = np.repeat(np.arange(len(low)), size)
    return np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size) + low[of], of


def scan_shard(docs: list[np.ndarray], phrases: Phrases) -> tuple[list[list[tuple[int, int]]], list[list[str]]]:
    """Merged spans of hit words and names of the items found, for each document of a shard."""
    sizes = np.fromiter(map(len, docs), np.int64, len(docs))
    stop = np.zeros(1, np.int32)
    whole = np.concatenate([y for x in docs for y in (x, stop)]) if docs else stop
    ends = np.cumsum(sizes + 1)
    spans, names = [[] for _ in docs], [[] for _ in docs]
    keep = np.flatnonzero((whole > 0) | np.concatenate([[False], whole[:-1] > 0]))
    if not len(keep) or not len(phrases.sizes):
        return spans, names
    index = FMIndex(whole[keep], phrases.bits)
    which, low, high = index.search(phrases.rows, phrases.sizes)
    rows, of = _ranges(low, high)
    if not len(rows):
        return spans, names
    at, pattern = keep[index.locate(rows)], which[of]
    edges = np.zeros(len(whole) + 1, np.int64)
    np.add.at(edges, at, 1)
    np.add.at(edges, at + phrases.sizes[pattern], -1)
    hit = np.concatenate([[0], (np.cumsum(edges) > 0).astype(np.int8), [0]])
    begin, end = np.flatnonzero(np.diff(hit) == 1), np.flatnonzero(np.diff(hit) == -1)
    for d, a, b in zip(np.searchsorted(ends, begin, "right"), begin, end, strict=True):
        base = int(ends[d] - sizes[d] - 1)
        spans[d].append((int(a) - base, int(b) - base))
    pairs = np.unique(np.searchsorted(ends, at, "right") * len(phrases.sizes) + pattern)
    doc, pattern = pairs // len(phrases.sizes), pairs % len(phrases.sizes)
    owner, of = _ranges(phrases.owned[pattern], phrases.owned[pattern + 1])
    for pair in np.unique(doc[of] * len(phrases.names) + phrases.owners[owner]):
        names[pair // len(phrases.names)].append(phrases.names[pair % len(phrases.names)])
    return spans, names


def merged(spans: Iterable[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans in order; those that overlap or touch become one."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], b))
        else:
            out.append((a, b))
    return out


def pieces(text: bytes, most: int, overlap: int) -> Iterator[tuple[int, int, list[bytes]]]:
    """(offset in words, words that the piece before holds too, words) of the pieces of a text of about
    `most` bytes, cut between words."""
    marked, at, offset, last = text.translate(ALNUM), 0, 0, []
    while at < len(marked):
        end = at + most
        end = len(marked) if end >= len(marked) else marked.find(b" ", end)
        end = len(marked) if end < 0 else end
        words = marked[at:end].split()
        yield offset - len(last), len(last), last + words
        offset, last, at = offset + len(words), (last + words)[-overlap:] if overlap else [], end


def scan_texts(texts: list[bytes | None], blocks: Iterable[Phrases], window: int, shard_bytes: int) -> tuple[list[int], list[list], list[set]]:
    """Word counts, merged spans and names found of the texts of a run."""
    counts, spans, names = [0] * len(texts), [[] for _ in texts], [set() for _ in texts]
    for nth, phrases in enumerate(blocks):
        shard, size = [], 0

        def search() -> None:
            for (i, offset, _), found, items in zip(shard, *scan_shard([x for _, _, x in shard], phrases), strict=True):  # noqa: B023
                spans[i] += [(a + offset, b + offset) for a, b in found]
                names[i].update(items)

        for i, text in enumerate(texts):
            for offset, again, words in pieces(text or b"", shard_bytes, window - 1):
                if nth == 0:
                    counts[i] += len(words) - again
                if shard and size + len(words) > shard_bytes // 4:
                    search()
                    shard, size = [], 0
                shard.append((i, offset, phrases.symbols(words)))
                size += len(words)
        search()
    return counts, [merged(s) for s in spans], names


def phrase_blocks(work: Work, bench: DataFrame, item_col: str, text_col: str, window: int, block_bytes: int) -> DataFrame:
    """(block, bytes, phrases) of the benchmark, built by tasks; equal items meet once."""
    items = bench.select(F.col(item_col).cast("string").alias("item"), F.col(text_col).cast("string").alias("text")).filter("text is not null").distinct()
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    dealt = items.withColumn("block", F.pmod(F.xxhash64("item", "text"), F.lit(-(-total // block_bytes) or 1)))

    def build(rows: pa.Table) -> pa.Table:
        texts = rows["text"].to_pylist()
        held = Phrases(sorted(zip(rows["item"].to_pylist(), texts, strict=True), key=lambda x: (x[0] or "", x[1])), window)
        return pa.table({"block": rows["block"][:1], "bytes": [sum(len(t.encode()) for t in texts)], "phrases": pa.array([pickle.dumps(held)], pa.binary())})

    return work.table(dealt.groupBy("block").applyInArrow(build, "block long, bytes long, phrases binary"), "phrases")


def _one_by_one(sent: list) -> Iterator[Phrases]:
    """The blocks sent out, each forgotten by this worker before the next is read."""
    for x in sent:
        yield pickle.loads(x.value)
        vars(x).pop("_value", None)


def marked(
    docs: DataFrame, bench: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text",
    window: int = 13, shard_bytes: int = 6 << 20, block_bytes: int = 4 << 20, pass_bytes: int = 1 << 30,
) -> tuple[DataFrame, str]:
    """The rows of docs with a struct (n_words, spans, items) beside them, and that column's name."""
    spark, name = docs.sparkSession, "_found" + "_" * max(map(len, docs.columns))
    work, columns, at = Work(spark), docs.columns, docs.columns.index(text_col)
    blocks, passes, held = phrase_blocks(work, bench, item_col, item_text_col, window, block_bytes), [[]], 0
    for r in blocks.orderBy("block").toLocalIterator():  # one block at a time
        if held and held + r["bytes"] > pass_bytes:
            passes.append([])
            held = 0
        passes[-1].append(spark.sparkContext.broadcast(bytes(r["phrases"])))
        held += r["bytes"]
    kind = pa.struct([("n_words", pa.int64()), ("spans", _SPANS), ("items", pa.list_(pa.string()))])
    out, schema = docs, StructType([*docs.schema.fields, StructField(name, _FOUND)])
    for k, sent in enumerate(passes):

        def run(batches: Iterator[pa.RecordBatch], sent=sent, k=k) -> Iterator[pa.RecordBatch]:
            make_room()
            one = pickle.loads(sent[0].value) if len(sent) == 1 else None
            for batch in batches:
                for a, b, texts in runs(batch.column(at), shard_bytes):
                    counts, spans, names = scan_texts(texts, [one] if one else _one_by_one(sent) if sent else [Phrases([], window)], window, shard_bytes)
                    part = batch.slice(a, b - a)
                    if k:
                        for i, was in enumerate(part.column(part.num_columns - 1).to_pylist()):
                            spans[i] = merged([*((s["start"], s["end"]) for s in was["spans"]), *spans[i]])
                            names[i].update(was["items"])
                    found = [{"n_words": n, "spans": [{"start": x, "end": y} for x, y in s], "items": sorted(m)} for n, s, m in zip(counts, spans, names, strict=True)]
                    yield pa.RecordBatch.from_arrays([*part.columns[: len(columns)], pa.array(found, kind)], names=[*columns, name])

        out = out.mapInArrow(run, schema)
        if k + 1 < len(passes):
            out = work.table(out, "marked")
    return out, name


def _hits(name: str):
    return F.aggregate(F.col(name)["spans"], F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["start"])


def contamination(docs: DataFrame, bench: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """doc_id, n_words, n_hit, spans (word offsets, merged) and items (names found, sorted)."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    out, name = marked(texts, bench, "text", **how)
    return out.select("doc_id", f"{name}.n_words", _hits(name).alias("n_hit"), f"{name}.spans", f"{name}.items")


def decontaminated(docs: DataFrame, bench: DataFrame, text_col: str = "text", least: int = 20, **how) -> DataFrame:
    """The documents of which less than one word in `least` is hit, with all their columns."""
    out, name = marked(docs, bench, text_col, **how)
    return out.filter((_hits(name) == 0) | (least * _hits(name) < F.col(name)["n_words"])).select(docs.columns)


def cleaned(docs: DataFrame, bench: DataFrame, text_col: str = "text", **how) -> DataFrame:
    """All documents, with the words of the benchmark's windows taken out of their texts."""
    out, name = marked(docs, bench, text_col, **how)
    columns, at, found = docs.columns, docs.columns.index(text_col), len(docs.columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in runs(batch.column(at)):
                part = batch.slice(a, b - a)
                spans = [[(s["start"], s["end"]) for s in x["spans"]] for x in part.column(found).to_pylist()]
                left = pa.array([without_spans(t.decode("utf-8", "replace") if t is not None else None, s) for t, s in zip(texts, spans, strict=True)], pa.string())
                yield pa.RecordBatch.from_arrays([left if i == at else c for i, c in enumerate(part.columns[:found])], names=columns)

    return out.mapInArrow(run, docs.schema)


def without_spans(text: str | None, spans: list[tuple[int, int]]) -> str | None:
    """The text without the words of the spans; the rest keeps its own characters."""
    if not text or not spans:
        return text
    raw, words = text.encode(), []
    marked, at = raw.translate(ALNUM), 0
    for w in marked.split():
        at = marked.index(w, at)
        words.append((at, at + len(w)))
        at += len(w)
    out, last = [], 0
    for start, end in spans:
        out.append(raw[last : words[start][0]])
        last = words[end - 1][1]
    return (b"".join(out) + raw[last:]).decode("utf-8", "replace")
