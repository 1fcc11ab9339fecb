"""License scans with ordered signature rules.

Each rule is a regex over the text's normalised words (ASCII lower case, words joined by one space),
with a label, a priority, a reliability and one keyword that every match holds. A keyword automaton
reads the text once; only rules whose keyword occurs run. Detections are ordered by priority, then
length, then place; one whose interval lies inside an accepted one of at least its priority is
suppressed. The rules are the hand-written ones of signatures.py: wording of the licences themselves,
tags, grants, versions and names.

Base phrases are found at every place their words stand in a row and are never suppressed. Defined
results: null and empty texts have no words, no detections and score 0; detections equal in priority and
length go by place, then by the order of the rules; repeated rows scan alike; long texts are read once.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellbalance.llm.common import ALNUM, runs
from cellbalance.llm.signatures import SIGNATURES

#: Base phrases and their labels.
BASE = (("gnu general public license", "gpl"), ("apache license", "apache"), ("cc by", "cc-by"), ("mit license", "mit"))


@dataclass(frozen=True)
class Rule:
    label: str
    pattern: str
    keyword: str
    priority: int
    reliability: float


_LINE = re.compile(r"(\S+) (\d+) (\d\.\d+) \[([^]]+)\] (.+)")


def rules(text: str = SIGNATURES) -> list[Rule]:
    """Every signature, in order of priority."""
    parsed = [_LINE.fullmatch(line) for line in text.strip().splitlines()]
    return sorted((Rule(m[1], m[5], m[4], int(m[2]), float(m[3])) for m in parsed), key=lambda r: (-r.priority, r.label, r.pattern))


class Scanner:
    def __init__(self, table: list[Rule]):
        self.rules = [(r, re.compile(f"(?<= )(?:{r.pattern})(?= )")) for r in table]
        self.words = ahocorasick.Automaton()
        by: dict[str, list[int]] = {}
        for i, r in enumerate(table):
            by.setdefault(f" {r.keyword} ", []).append(i)
        for key, ids in by.items():
            self.words.add_word(key, ids)
        self.words.make_automaton()

    def detections(self, normal: str) -> list[tuple[int, int, Rule]]:
        """Accepted (start, end, rule), in characters of the normalised text."""
        run = sorted({i for _, ids in self.words.iter(normal) for i in ids})
        found = [(m.start(), m.end(), i) for i in run for m in self.rules[i][1].finditer(normal)]
        found.sort(key=lambda d: (-self.rules[d[2]][0].priority, d[0] - d[1], d[0], d[2]))
        kept, reach = [], Reach([a for a, _, _ in found])
        for a, b, i in found:
            if reach.upto(a) < b:
                kept.append((a, b, self.rules[i][0]))
                reach.put(a, b)
        return kept


class Reach:
    """The furthest end among intervals put so far that start at or before a place."""

    def __init__(self, starts: list[int]):
        self.starts = sorted(set(starts))
        self.most = [-1] * (len(self.starts) + 1)

    def put(self, start: int, end: int) -> None:
        i = bisect_right(self.starts, start)
        while i < len(self.most):
            self.most[i] = max(self.most[i], end)
            i += i & -i

    def upto(self, start: int) -> int:
        i, out = bisect_right(self.starts, start), -1
        while i:
            out = max(out, self.most[i])
            i -= i & -i
        return out


def scan_text(text: bytes | None, scanner: Scanner) -> dict:
    words = text.translate(ALNUM).split() if text else []
    raw = b" " + b" ".join(words) + b" "
    normal = raw.decode("latin-1")  # one character a byte; all patterns are ASCII
    places, base = [], set()
    for phrase, label in BASE:
        at = normal.find(f" {phrase} ")
        while at >= 0:
            places.append(at + 1)
            base.add(label)
            at = normal.find(f" {phrase} ", at + 1)
    spans = scanner.detections(normal)
    gaps = np.flatnonzero(np.frombuffer(raw, np.uint8) == 32) if places or spans else np.zeros(0, np.int64)
    nth = lambda at: int(np.searchsorted(gaps, at)) - 1  # noqa: E731  which word starts at a character
    return {
        "n_words": len(words),
        "n_base": len(places),
        "first_word": nth(min(places)) if places else None,
        "last_word": nth(max(places)) if places else None,
        "base_labels": sorted(base),
        "labels": sorted(base | {r.label for _, _, r in spans}),
        "score": max([0.6 * bool(places), *(r.reliability for _, _, r in spans)]),
        "detections": [{"start": nth(a), "end": nth(b) + 1, "label": r.label, "priority": r.priority} for a, b, r in spans],
    }


_SCANNERS: dict[tuple, Scanner] = {}
_SCHEMA = (
    "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels array<string>, labels array<string>, "
    "score double, detections array<struct<start:long,end:long,label:string,priority:long>>"
)
_ARROW = pa.struct(
    [("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.list_(pa.string())),
     ("labels", pa.list_(pa.string())), ("score", pa.float64()),
     ("detections", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("label", pa.string()), ("priority", pa.int64())])))]
)


def scan(docs: DataFrame, table: list[Rule] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Counts, labels, score and accepted detections (word spans) of every row."""
    chosen = tuple(table if table is not None else rules())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if chosen not in _SCANNERS:
            _SCANNERS.clear()
            _SCANNERS[chosen] = Scanner(list(chosen))
        for batch in batches:
            for a, b, texts in runs(batch.column(1)):
                found = pa.array([scan_text(t, _SCANNERS[chosen]) for t in texts], _ARROW)
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], *found.flatten()], names=["doc_id", *(f.name for f in _ARROW)])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, _SCHEMA)
