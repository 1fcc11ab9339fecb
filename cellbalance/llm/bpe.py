"""Byte-level BPE with a contiguous rank array per word.

A word's parts stand in one array and the ranks of adjacent parts in another. The smallest rank is
found by a scan, its boundary is deleted from both arrays, and the two neighbouring ranks are looked
up anew, until no pair has a rank. Words over `LONG` parts, where scans would cost the square, keep
their ranks in a heap over linked parts; the order of merges is the same. Words up to
that length are encoded many at a time, one rank array per row of a matrix. Pieces met before are
remembered, a bounded number per worker.

Vocabulary, merges, added tokens and byte alphabet come from a tokenizer file given by path. Defined
results: a null or empty text encodes to no ids and decodes to the empty string; added tokens in a
text are found first, the leftmost and of those the longest.
"""

from __future__ import annotations

import heapq
import json
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellbalance.llm.common import MEMORIES, make_room, runs

#: Fixed value: the published pattern that splits text before byte-level merges.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
LONG = 64
KNOWN = 200_000
_NONE = 1 << 60


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = iter(range(256, 512))
    return [chr(b) if b in set(plain) else chr(next(other)) for b in range(256)]


class RankArrayBPE:
    def __init__(self, spec: bytes):
        spec = json.loads(spec)
        vocab, alphabet = spec["model"]["vocab"], byte_alphabet()
        back = {c: b for b, c in enumerate(alphabet)}
        self.byte_ids = [vocab[c] for c in alphabet]
        self.ranks, self.merged = {}, []
        for rank, pair in enumerate(spec["model"]["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            self.ranks.setdefault(vocab[left] << 32 | vocab[right], rank)
            self.merged.append(vocab[left + right])
        self.bytes_of = {i: bytes(back[c] for c in token) for token, i in vocab.items()}
        self.added = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.bytes_of |= {i: t.encode() for t, i in self.added.items()}
        self.special = regex.compile("|".join(map(regex.escape, sorted(self.added, key=len, reverse=True)))) if self.added else None
        self.split = regex.compile(PATTERN).findall
        self.known: dict[str, bytes] = {}
        self._table()

    def _table(self) -> None:
        """Pair ranks in an open-addressing table, for many pairs at once."""
        self.shift = 64 - max(4, (4 * len(self.ranks)).bit_length())
        size = 1 << (64 - self.shift)
        self.keys, self.values = np.full(size, -1, np.int64), np.full(size, _NONE, np.int64)
        keys, values = np.fromiter(self.ranks, np.int64, len(self.ranks)), np.fromiter(self.ranks.values(), np.int64, len(self.ranks))
        at, todo = self._slot(keys), np.arange(len(keys))
        while len(todo):
            free = todo[self.keys[at[todo]] < 0]
            won = free[np.unique(at[free], return_index=True)[1]]
            self.keys[at[won]], self.values[at[won]] = keys[won], values[won]
            todo = todo[~np.isin(todo, won)]
            at[todo] = (at[todo] + 1) % size
        self.byte_row, self.merged_row = np.array(self.byte_ids), np.array([*self.merged, 0])

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(self.shift)).astype(np.int64)

    def _rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Ranks of pairs; a negative part ends a word and has no pair."""
        key = left << 32 | np.maximum(right, 0)
        out, at, todo = np.full(len(key), _NONE), self._slot(key), np.flatnonzero((left >= 0) & (right >= 0))
        while len(todo):
            held = self.keys[at[todo]]
            same = held == key[todo]
            out[todo[same]] = self.values[at[todo[same]]]
            todo = todo[~same & (held >= 0)]
            at[todo] = (at[todo] + 1) & (len(self.keys) - 1)
        return out

    def encode_words(self, words: list[bytes]) -> list[bytes]:
        """Ids of each word, as bytes. Short words of like length share a matrix, one rank array a row."""
        out: list[bytes] = [b""] * len(words)
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        for low, high in ((0, 8), (8, 16), (16, 32), (32, LONG)):
            chosen = np.flatnonzero((sizes > low) & (sizes <= high))
            if len(chosen):
                for i, ids in zip(chosen, self._matrix([words[i] for i in chosen], high), strict=True):
                    out[i] = ids
        for i in np.flatnonzero(sizes > LONG):
            out[i] = np.array(self.word(words[i]), "<u4").tobytes()
        return out

    def _matrix(self, words: list[bytes], width: int) -> list[bytes]:
        raw = np.frombuffer(b"".join(w.ljust(width, b"\0") for w in words), np.uint8).reshape(-1, width)
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        column = np.arange(width)
        parts = np.where(column < sizes[:, None], self.byte_row[raw], -1)
        ranks = np.full(parts.shape, _NONE)
        ranks[:, :-1] = self._rank(parts[:, :-1].ravel(), parts[:, 1:].ravel()).reshape(len(words), -1)
        done, live = parts.copy(), np.arange(len(words))
        while True:
            at = ranks.argmin(1)
            least = ranks[np.arange(len(live)), at]
            open_ = least < _NONE
            if not open_.all():
                done[live[~open_]] = parts[~open_]
                live, parts, ranks, at, least = live[open_], parts[open_], ranks[open_], at[open_], least[open_]
            if not len(live):
                break
            row, later = np.arange(len(live)), column[:-1] > at[:, None]
            parts[row, at] = self.merged_row[least]
            parts[:, :-1] = np.where(later, parts[:, 1:], parts[:, :-1])
            parts[:, -1] = -1
            ranks[:, :-1] = np.where(later, ranks[:, 1:], ranks[:, :-1])
            ranks[:, -1] = _NONE
            ranks[row, at] = self._rank(parts[row, at], parts[row, np.minimum(at + 1, width - 1)])
            inner = np.flatnonzero(at > 0)
            ranks[inner, at[inner] - 1] = self._rank(parts[inner, at[inner] - 1], parts[inner, at[inner]])
        flat = done[done >= 0].astype("<u4").tobytes()
        ends = np.concatenate([[0], np.cumsum((done >= 0).sum(1))]) * 4
        return [flat[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]

    def word(self, raw: bytes) -> list[int]:
        parts = [self.byte_ids[b] for b in raw]
        if len(parts) > LONG:
            return self._long(parts)
        get, merged = self.ranks.get, self.merged
        ranks = [get(a << 32 | b, _NONE) for a, b in zip(parts, parts[1:])]
        while ranks:
            least = min(ranks)
            if least == _NONE:
                break
            i = ranks.index(least)
            part = parts[i] = merged[least]
            del parts[i + 1], ranks[i]
            if i < len(ranks):
                ranks[i] = get(part << 32 | parts[i + 1], _NONE)
            if i:
                ranks[i - 1] = get(parts[i - 1] << 32 | part, _NONE)
        return parts

    def _long(self, parts: list[int]) -> list[int]:
        n, get = len(parts), self.ranks.get
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        queue = [(get(parts[i] << 32 | parts[i + 1], _NONE), i) for i in range(n - 1)]
        queue = [x for x in queue if x[0] < _NONE]
        heapq.heapify(queue)
        while queue:
            rank, i = heapq.heappop(queue)
            j = after[i]
            # stale where the left part is gone, has no right part, or the pair has another rank now
            if parts[i] < 0 or j < 0 or get(parts[i] << 32 | parts[j], _NONE) != rank:
                continue
            parts[i], parts[j], after[i] = self.merged[rank], -1, after[j]
            if after[j] >= 0:
                before[after[j]] = i
            for a, b in ((before[i], i), (i, after[i])):
                if a >= 0 and b >= 0 and (r := get(parts[a] << 32 | parts[b], _NONE)) < _NONE:
                    heapq.heappush(queue, (r, a))
        return [p for p in parts if p >= 0]

    def pieces(self, text: str) -> list[str | int]:
        """Runs between added tokens, cut before single spaces, and the added tokens' ids. A cut
        before one space is where the pattern cuts too; runs with two spaces in a row stay whole."""
        out, last = [], 0
        found = self.special.finditer(text) if self.special and any(t in text for t in self.added) else ()
        for start, end, token in [*((m.start(), m.end(), self.added[m[0]]) for m in found), (len(text), 0, None)]:
            if run := text[last:start]:
                if "  " in run or run[-1] == " ":
                    out.append(run)
                else:
                    head, *rest = run.split(" ")
                    out.extend([head] if head else [])
                    out.extend([" " + x for x in rest])
            if token is not None:
                out.append(token)
            last = end
        return out

    def encode_many(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        cut = [self.pieces(t) for t in texts]
        fresh = set(chain.from_iterable(cut)).difference(self.known)
        split = {p: [p] if isinstance(p, int) else self.split(p) for p in fresh}
        words = list({w for ws in split.values() for w in ws})
        ids = dict(zip(words, self.encode_words([w.encode() if isinstance(w, str) else b"" for w in words]), strict=True))
        ids |= {w: np.array([w], "<u4").tobytes() for w in words if isinstance(w, int)}
        now = {p: b"".join([ids[w] for w in ws]) for p, ws in split.items()}
        known = self.known | now if len(self.known) + len(now) > KNOWN else self.known
        if known is self.known:
            known.update(now)
        else:
            self.known = {}
        out = [b"".join(map(known.__getitem__, c)) for c in cut]
        for p in [p for p in now if isinstance(p, str) and len(p) > LONG]:
            self.known.pop(p, None)
        return out

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")


_LOADED: dict[bytes, RankArrayBPE] = MEMORIES.setdefault("bpe", {})


def _loaded(spec: bytes) -> RankArrayBPE:
    """One tokenizer per worker process, so remembered words outlive a task."""
    make_room("bpe")
    if spec not in _LOADED:
        _LOADED.clear()
        _LOADED[spec] = RankArrayBPE(spec)
    return _LOADED[spec]


def _spec(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def encode(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens and ids, little-endian unsigned 32-bit integers in one binary value."""
    sent = docs.sparkSession.sparkContext.broadcast(_spec(tokenizer_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = _loaded(sent.value)
        for batch in batches:
            for a, b, texts in runs(batch.column(1), 1 << 20):
                ids = bpe.encode_many([t.decode("utf-8", "replace") if t else "" for t in texts])
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())], names=["doc_id", "n_tokens", "ids"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, n_tokens long, ids binary")


def decode(encoded: DataFrame, tokenizer_path: str) -> DataFrame:
    """The rows of encode() with the decoded text."""
    sent = encoded.sparkSession.sparkContext.broadcast(_spec(tokenizer_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = _loaded(sent.value)
        for batch in batches:
            for a, b, ids in runs(batch.column(2), 1 << 20):
                texts = [bpe.decode(np.frombuffer(x or b"", "<u4").tolist()) for x in ids]
                yield pa.RecordBatch.from_arrays([*(c[a:b] for c in batch.columns), pa.array(texts, pa.string())], names=[*batch.schema.names, "decoded"])

    return encoded.select("doc_id", "n_tokens", "ids").mapInArrow(run, "doc_id long, n_tokens long, ids binary, decoded string")


def round_trip(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """encode() and decode() in one pass: doc_id, n_tokens, ids, decoded."""
    sent = docs.sparkSession.sparkContext.broadcast(_spec(tokenizer_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = _loaded(sent.value)
        for batch in batches:
            for a, b, texts in runs(batch.column(1), 1 << 20):
                ids = bpe.encode_many([t.decode("utf-8", "replace") if t else "" for t in texts])
                back = [bpe.decode(np.frombuffer(x, "<u4").tolist()) for x in ids]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0)[a:b], pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary()), pa.array(back, pa.string())],
                    names=["doc_id", "n_tokens", "ids", "decoded"],
                )

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return texts.mapInArrow(run, "doc_id long, n_tokens long, ids binary, decoded string")
