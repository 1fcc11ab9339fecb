"""Quality rules by compression bands.

A text's bytes go through zstandard as a whole and in fixed chunks, the shorter last one included. The
ratio of raw to compressed size has a band for each length class: above it the text repeats itself, below
it it is noise such as encoded binary. A text is kept if the whole lies in its band and at most
`bad_share` of its chunks leave the band of their own length; a text of one chunk is judged as a whole.
Frames carry a fixed cost, which is taken off before the ratio, so short texts compare.

Base counts follow fixed rules: code points in words, symbol characters, repeated lines, and words
covered by word windows that occur twice or more in the same text. Defined results: a null or empty
text has zeros everywhere and fails the base rule; repeated rows are judged alike.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellbalance.llm.common import Interned, mix64, runs

SPACES = b" \t\n\r\x0b\x0c"
CONTINUATIONS = bytes(range(0x80, 0xC0))
SYMBOLS = b"#*$%&|<>"
WINDOW, CHUNK, FRAME = 8, 4096, 9
#: Upper length in bytes, least and greatest ratio.
BANDS = ((256, 0.8, 3.5), (1024, 1.05, 4.5), (4096, 1.2, 6.0), (16384, 1.4, 8.0), (65536, 1.5, 10.0), (1 << 62, 1.6, 12.0))
_STEP = np.uint64(0x9E3779B97F4A7C15)
_WORDS = Interned(xxhash.xxh3_64_intdigest)


def band(n: int) -> tuple[float, float]:
    return next((low, high) for most, low, high in BANDS if n <= most)


def repeated_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words inside windows whose words occur at two or more places."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    w = np.fromiter(map(_WORDS.__getitem__, words), np.uint64, len(words))
    rolled = w[:n].copy()
    for j in range(1, window):
        rolled = rolled * _STEP + w[j : j + n]
    rolled = mix64(rolled)
    order = np.argsort(rolled)
    same = rolled[order[1:]] == rolled[order[:-1]]
    if not same.any():
        return 0
    twice = np.zeros(n, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edges = np.zeros(len(words) + 1, np.int32)
    edges[:n] += twice
    edges[window : window + n] -= twice
    return int((np.cumsum(edges[:-1]) > 0).sum())


def repeated_lines(text: bytes) -> int:
    seen, n = set(), 0
    for line in text.split(b"\n"):
        if line.strip(SPACES):
            n += line in seen
            seen.add(line)
    return n


def ratio_of(block: bytes, press) -> float:
    return len(block) / max(1, len(press(block)) - FRAME)


def in_its_band(block: bytes, press) -> bool:
    low, high = band(len(block))
    return low <= ratio_of(block, press) <= high


def measure(text: bytes, press) -> tuple:
    words = text.split()
    ratio = ratio_of(text, press) if text else 0.0
    starts = range(0, len(text), CHUNK) if len(text) > CHUNK else ()
    bad = sum(not in_its_band(text[a : a + CHUNK], press) for a in starts)
    return (
        len(words),
        len(text.translate(None, SPACES + CONTINUATIONS)),
        len(text) - len(text.translate(None, SYMBOLS)),
        repeated_lines(text),
        repeated_words(words),
        ratio,
        len(starts),
        bad,
    )


_FIELDS = (("n_words", "long"), ("word_chars", "long"), ("n_symbols", "long"), ("n_dup_lines", "long"), ("n_repeat_words", "long"), ("ratio", "double"), ("n_chunks", "long"), ("bad_chunks", "long"))


def compression_bands(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", level: int = 3, bad_share: float = 0.25) -> DataFrame:
    """doc_id, the counts, ratio, chunks, in_band, base_failed and kept of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=level, write_checksum=False).compress
        for batch in batches:
            for a, b, texts in runs(batch.column(1)):
                columns = zip(*(measure(t or b"", press) for t in texts), strict=True)
                arrays = [pa.array(c, pa.float64() if kind == "double" else pa.int64()) for c, (_, kind) in zip(columns, _FIELDS, strict=True)]
                arrays.append(pa.array([len(t or b"") for t in texts], pa.int64()))
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], *arrays], names=["doc_id", *(n for n, _ in _FIELDS), "n_bytes"])

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    measured = texts.mapInArrow(run, "doc_id long, " + ", ".join(f"{n} {k}" for n, k in _FIELDS) + ", n_bytes long")
    low, high = F.lit(BANDS[-1][1]), F.lit(BANDS[-1][2])
    for most, a, b in reversed(BANDS[:-1]):
        low, high = F.when(F.col("n_bytes") <= most, F.lit(a)).otherwise(low), F.when(F.col("n_bytes") <= most, F.lit(b)).otherwise(high)
    return measured.withColumn("in_band", F.col("ratio").between(low, high) & (F.col("bad_chunks") <= bad_share * F.col("n_chunks"))).withColumn(
        "base_failed", F.expr("n_words < 20 or 100 * n_repeat_words > 30 * n_words")
    ).withColumn("kept", ~F.col("base_failed") & F.col("in_band"))
