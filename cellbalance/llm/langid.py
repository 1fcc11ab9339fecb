"""Hierarchical language identification: family first, then one-versus-one linear SVMs within it.

Features are hashed counts of byte pairs and triples of the whole text (ASCII letters lower-cased), added
up megabyte by megabyte, square-rooted and scaled to length one. At either level each pair of classes has a
linear SVM (squared hinge, batch gradient); the class with most votes wins, ties go to the larger sum of
margins. Models are fitted on a bounded sample, `per_class` rows per language at expectation, chosen by a
hash of the id among rows that the caller allows. Each pair of classes is a task of its own, which holds
the sample's rows of these two classes; the driver gets weights only. Everything else runs over all rows.

Defined results: null texts and texts without a letter are `und` with score 0; with no labelled row
every text is `und`; with one language every text with a letter is that language. Rows with a null
label are never learned from. Repeated rows are scored alike.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
import regex
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellbalance.llm.common import LOWER, Work, keep_rows, make_room, runs

#: Language codes by family; a code not listed is a family of its own.
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af fy lb yi",
    "romance": "fr es pt it ro ca gl oc la",
    "slavic": "ru uk be pl cs sk bg sr hr bs sl mk",
    "baltic": "lt lv",
    "uralic": "fi et hu",
    "turkic": "tr az kk ky uz tk tt",
    "indic": "hi bn mr gu pa ne ur si",
    "dravidian": "ta te kn ml",
    "semitic": "ar he am mt",
    "sinitic": "zh yue wuu",
}
_FAMILY = {code: family for family, codes in FAMILIES.items() for code in codes.split()}
WIDTH = 4096
_LETTER = regex.compile(r"\p{L}").search


def features(texts: list[bytes]) -> np.ndarray:
    """Hashed counts of byte pairs and triples, one row a text."""
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    flat = np.frombuffer(b"".join(texts).translate(LOWER) + b"\0\0", np.uint8).astype(np.uint32)
    row = np.repeat(np.arange(len(texts)) * WIDTH, sizes)
    ends = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(row))
    pair = flat[:-2] * np.uint32(256) + flat[1:-1]
    triple = (pair * np.uint32(256) + flat[2:]) * np.uint32(2654435761) >> np.uint32(20)
    pair = (pair + np.uint32(77)) * np.uint32(2246822519) >> np.uint32(20)
    n = len(texts) * WIDTH
    out = np.bincount((row + pair)[ends > 1], minlength=n) + np.bincount((row + triple)[ends > 2], minlength=n)
    return out.reshape(len(texts), WIDTH)


def text_features(text: bytes, most: int = 1 << 20) -> np.ndarray:
    """features() of one text of any length: pieces overlap by the two bytes that pairs and triples span."""
    out = np.zeros(WIDTH, np.int64)
    for a in range(0, max(1, len(text)), most):
        piece = text[a : a + most + 2]
        out += features([piece])[0]
        if a + most < len(text):  # what starts in the overlap is counted with the next piece
            out -= features([piece[most:]])[0]
    return out


def counted(texts: list[bytes], most: int = 1 << 20) -> np.ndarray:
    if len(texts) == 1 and len(texts[0]) > most:
        return text_features(texts[0], most)[None]
    return features(texts)


def scaled(counts: np.ndarray) -> np.ndarray:
    x = np.sqrt(counts.astype(np.float32))
    return x / np.maximum(np.sqrt((x * x).sum(1, keepdims=True)), 1e-9)


def linear_svm(x: np.ndarray, y: np.ndarray, c: float = 30.0, rounds: int = 120) -> np.ndarray:
    """Weights and bias for labels +1 and -1: squared hinge with classes weighed alike, accelerated gradient."""
    x = np.hstack([x, np.ones((len(x), 1), np.float32)])
    share = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum())).astype(np.float32)
    w = v = np.zeros(x.shape[1], np.float32)
    step, t = 1.0 / (1.0 + 4.0 * c), 1.0
    for _ in range(rounds):
        slack = np.maximum(0, 1 - y * (x @ v))
        new = v - step * (v - 2 * c * (x.T @ (share * y * slack)))
        nxt = (1 + (1 + 4 * t * t) ** 0.5) / 2  # a Python float keeps the weights in single precision
        v, w, t = new + (t - 1) / nxt * (new - w), new, nxt
    return w


@dataclass
class Pairwise:
    classes: list[str]
    weights: np.ndarray

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of the class and how sure its closest duel is."""
        k = len(self.classes)
        votes, sums, least = np.zeros((len(x), k)), np.zeros((len(x), k)), np.full((len(x), k), np.inf)
        margins = x @ self.weights[:, :-1].T + self.weights[:, -1]
        for j, (a, b) in enumerate(combinations(range(k), 2)):
            m = margins[:, j]
            votes[:, a] += m > 0
            votes[:, b] += m <= 0
            for i, s in ((a, m), (b, -m)):
                sums[:, i] += s
                least[:, i] = np.minimum(least[:, i], s)
        best = np.lexsort((sums, votes), axis=1)[:, -1] if k > 1 else np.zeros(len(x), np.int64)
        sure = 1 / (1 + np.exp(-4 * np.minimum(least[np.arange(len(x)), best], 50)))
        return best, sure


@dataclass
class Hierarchy:
    families: Pairwise
    within: dict[str, Pairwise]

    def predict(self, texts: list[bytes]) -> tuple[list[str], np.ndarray]:
        x = scaled(counted(texts))
        family, sure = self.families.predict(x)
        names, score = [""] * len(texts), sure.astype(float)
        for f in set(family.tolist()):
            of, model = np.flatnonzero(family == f), self.within[self.families.classes[f]]
            best, inner = model.predict(x[of])
            score[of] *= inner
            for i, b in zip(of.tolist(), best.tolist(), strict=True):
                names[i] = model.classes[b]
        return names, score


def duels(languages: list[str]) -> list[tuple[str, str, str, list[str], list[str]]]:
    """(level, a, b, languages of a, languages of b): a pair of classes each, families at level ''."""
    families: dict[str, list[str]] = {}
    for code in sorted(languages):
        families.setdefault(_FAMILY.get(code, code), []).append(code)
    out = [("", a, b, families[a], families[b]) for a, b in combinations(sorted(families), 2)]
    return out + [(f, a, b, [a], [b]) for f, codes in sorted(families.items()) for a, b in combinations(codes, 2)]


def fit(docs: DataFrame, allowed: Column, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang", per_class: int = 800) -> Hierarchy | None:
    """A model from about `per_class` allowed rows of each label; every duel is fitted by a task."""
    spark, work = docs.sparkSession, Work(docs.sparkSession)
    known = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), F.col(label_col).cast("string").alias("label"), allowed.alias("may"))
    known = known.filter("may and label is not null and text is not null")
    held = {r["label"]: r["n"] for r in known.groupBy("label").agg(F.count("*").alias("n")).collect()}
    if not held:
        return None
    share = F.lit(0)
    for label, n in held.items():
        share = F.when(F.col("label") == label, F.lit(int(min(1.0, per_class / n) * (1 << 32)))).otherwise(share)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        press = zstandard.ZstdCompressor(level=1).compress  # most counts are small or nought
        for batch in batches:
            for a, b, texts in runs(batch.column(1), 1 << 18):
                counts = counted(texts).astype("<u4")
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], pa.array([press(r.tobytes()) for r in counts], pa.binary())], names=["label", "counts"])

    chosen = known.filter(F.pmod(F.xxhash64("id", "text"), F.lit(1 << 32)) < share).select("label", "text").mapInArrow(run, "label string, counts binary")
    chosen = work.table(chosen, "features")
    present = sorted(r["label"] for r in chosen.select("label").distinct().collect())
    table = duels(present)
    sides = [(i, code, side) for i, d in enumerate(table) for side, codes in ((1, d[3]), (-1, d[4])) for code in codes]

    def train(rows: pa.Table) -> pa.Table:
        make_room()
        unpress = zstandard.ZstdDecompressor().decompress
        counts = np.frombuffer(b"".join(map(unpress, sorted(rows["counts"].to_pylist()))), "<u4").reshape(-1, WIDTH)
        sign = [s for _, s in sorted(zip(rows["counts"].to_pylist(), rows["side"].to_pylist(), strict=True))]
        w = linear_svm(scaled(counts), np.array(sign, np.float32))
        return pa.table({"duel": rows["duel"][:1], "weights": pa.array([w.tobytes()], pa.binary())})

    found: dict[int, np.ndarray] = {}
    if sides:
        dealt = chosen.join(F.broadcast(spark.createDataFrame(sides, "duel int, label string, side int")), "label")
        for r in dealt.repartition(len(table), "duel").groupBy("duel").applyInArrow(train, "duel int, weights binary").collect():
            found[r["duel"]] = np.frombuffer(bytes(r["weights"]), np.float32)

    def level(name: str, classes: list[str]) -> Pairwise:
        rows = [found[i] for i, d in enumerate(table) if d[0] == name]
        return Pairwise(classes, np.array(rows, np.float32).reshape(len(rows), WIDTH + 1))

    families = sorted({_FAMILY.get(c, c) for c in present})
    return Hierarchy(level("", families), {f: level(f, [c for c in present if _FAMILY.get(c, c) == f]) for f in families}) if present else None


def judged(texts: list[bytes | None], model: Hierarchy | None) -> tuple[list[str], list[float]]:
    """Language and score of each text, 64 at a time."""
    names, score = ["und"] * len(texts), [0.0] * len(texts)
    lettered = [i for i, t in enumerate(texts) if t and model and _LETTER(t.decode("utf-8", "replace"))]
    for a in range(0, len(lettered), 64):
        part = lettered[a : a + 64]
        for i, name, s in zip(part, *model.predict([texts[i] for i in part]), strict=True):
            names[i], score[i] = name, float(s)
    return names, score


def identify(docs: DataFrame, model: Hierarchy | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, lang_pred, score of every row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in runs(batch.column(1), 1 << 20):
                names, score = judged(texts, sent.value)
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], pa.array(names, pa.string()), pa.array(score, pa.float64())], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, lang_pred string, score double")


def in_known_language(docs: DataFrame, model: Hierarchy | None, text_col: str = "text") -> DataFrame:
    """The documents that get a language, with all their columns."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    return keep_rows(docs, text_col, lambda texts: [name != "und" for name in judged(texts, sent.value)[0]], 1 << 20)


def held_out(labels: list[str], predicted: list[str]) -> dict[str, float]:
    """Share of right predictions for each label."""
    all_, right = Counter(labels), Counter(a for a, b in zip(labels, predicted, strict=True) if a == b)
    return {k: right[k] / n for k, n in all_.items()}
