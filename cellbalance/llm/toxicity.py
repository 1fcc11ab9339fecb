"""Toxicity by a weighted finite-state pattern grammar.

A lexical transducer (a weighted trie over word beginnings) turns words into classes: insult, harm
verb, first person, modal, target, copula, negation, report verb, quote, boundary, other. Four more
transducers read and rewrite classes: negation marks what stands in its scope, reported speech marks
what follows a report verb or stands in quotes, threats need first person, modal and harm verb in
order, and targets let an insult fire only where its clause aims it at somebody: an addressee before or
after it, or a copula that predicates it. They are composed into one deterministic machine. A fifth one
runs beside it, since its states are words: an insult that follows a different insult of the same text
is one of a pile. What matches nothing scores nothing: a single insult that is aimed at nobody is a word
by itself. Matched weights add up by pattern (aimed, piled, threat, told, the last for any of them in
reported speech), and a logistic with one weight a pattern gives the score.

The insult arcs are learned: word beginnings of 4 to 12 letters that mark toxic rows of the allowed
part of the labels, picked greedily so that each one explains toxic rows not yet explained; a
hand-written seed list joins them. The weights of the patterns are learned from the same rows, drawn to
hand-set values where rows say little; the score of a text that matches nothing is fixed. The fit uses a
bounded sample, about `positives` and `negatives` of the allowed rows, which alone set its rate.

Defined results: null and empty texts have no match and get the score of no match; a document with several
labels is toxic if one of them says so; without labels the seed lexicon and hand-set weights decide;
repeated rows score alike; very long texts are read from start to end.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellbalance.llm.common import Interned, keep_rows, runs

#: Seed words by class.
SEEDS = {
    "insult": "idiot moron imbecile scum loser worthless pathetic disgusting stupid trash clown idioten trottel arschloch dummkopf abschaum imbécile crétin connard ordure idiota imbécil estúpido basura",
    "harm": "kill hurt destroy beat stab shoot murder töten schlagen tuer frapper matar golpear",
    "self": "i we ich wir je nous yo nosotros",
    "modal": "will shall gonna would werde werden vais allons voy vamos",
    "target": "you your you're he she they them him her he's she's they're du dein sie ihr dich er tu toi vous votre il elle ils elles tú usted ustedes él ella ellos",
    "copula": "is are was were be been being ist sind war bist seid est êtes sont était es son era eres",
    "negation": "not never no don't isn't aren't wasn't won't nicht kein keine nie ne pas jamais ni nunca jamás",
    "report": "said says wrote claimed called reported quoted sagte schrieb nannte dit écrit déclaré dijo escribió llamó",
    "boundary": "but although because aber obwohl weil mais parce pero porque",
}
CLASSES = ("other", "insult", "harm", "self", "modal", "target", "copula", "negation", "report", "quote", "boundary")
#: Score of a text without a match, as a logit, and the weight of each pattern before rows are seen.
NO_MATCH = -3.0
PRIOR = {"aimed": 2.4, "piled": 1.6, "threat": 2.5, "told": 0.9}
_TOKEN = re.compile(r"[^\W\d_]+(?:['’][^\W\d_]+)?|[.!?;:,\n|]|[\"“”«»„]").findall
_PUNCTUATION = dict.fromkeys(".!?;:,\n|", "boundary") | dict.fromkeys('"“”«»„', "quote")


class Transducer:
    """Deterministic: (state, symbol) to (state, symbol, weight); a missing arc keeps both."""

    def __init__(self, start, arcs: dict):
        self.start, self.arcs = start, arcs

    def step(self, state, symbol: str) -> tuple:
        return self.arcs.get((state, symbol), (state, symbol, 1.0))

    def then(self, other: Transducer, symbols: Iterable[str]) -> Transducer:
        """Composition: what this one writes, the other reads."""
        start, arcs, todo = (self.start, other.start), {}, [(self.start, other.start)]
        seen = {start}
        while todo:
            a, b = todo.pop()
            for s in symbols:
                a2, mid, w1 = self.step(a, s)
                b2, out, w2 = other.step(b, mid)
                arcs[(a, b), s] = ((a2, b2), out, w1 * w2)
                if (a2, b2) not in seen:
                    seen.add((a2, b2))
                    todo.append((a2, b2))
        return Transducer(start, arcs)


def negation(scope: int = 3, factor: float = 0.3) -> Transducer:
    arcs = {}
    for left in range(scope + 1):
        arcs[left, "negation"] = (scope, "other", 1.0)
        arcs[left, "boundary"] = (0, "boundary", 1.0)
        for s in ("other", "target", "self", "modal", "copula", "report", "quote"):
            arcs[left, s] = (max(0, left - 1), s, 1.0)
        for s in ("insult", "harm"):
            arcs[left, s] = (max(0, left - 1), s, factor if left else 1.0)
    return Transducer(0, arcs)


def reported() -> Transducer:
    """Insults and harm verbs of reported speech are written as told ones; the report verb stays, so that
    who speaks is nobody's target."""
    arcs = {}
    for state in ("plain", "told", "quoted"):
        arcs[state, "report"] = ("told" if state == "plain" else state, "report", 1.0)
        arcs[state, "quote"] = ("plain" if state == "quoted" else "quoted", "other", 1.0)
        arcs[state, "boundary"] = ("quoted" if state == "quoted" else "plain", "boundary", 1.0)
        for s in ("insult", "harm"):
            arcs[state, s] = (state, s if state == "plain" else f"told {s}", 1.0)
    return Transducer("plain", arcs)


def threat() -> Transducer:
    """First person, then modal, then harm verb: a threat. A harm verb alone is other."""
    arcs = {(0, "self"): (1, "other", 1.0), (1, "self"): (1, "other", 1.0), (1, "modal"): (2, "other", 1.0), (2, "harm"): (2, "threat", 1.0), (2, "told harm"): (2, "told threat", 1.0)}
    for state in range(3):
        arcs[state, "boundary"] = (0, "boundary", 1.0)
        for s in ("harm", "told harm", "modal", "self"):
            arcs.setdefault((state, s), (state, "other", 1.0))
    return Transducer(0, arcs)


def target(boost: float = 1.5, reach: int = 3) -> Transducer:
    """Insults aimed at somebody fire. `aimed` follows its addressee or, within `reach` words, a copula;
    `claim` is an addressee that claims the insults before it in the clause, which were written as held."""
    arcs = {}
    states = ["none", "seen", "held", *range(1, reach + 1)]
    for state in states:
        copula = isinstance(state, int)
        later = (state - 1 or "none") if copula else state
        for s in ("other", "self", "modal", "negation", "quote"):
            arcs[state, s] = (later, "other", 1.0)
        arcs[state, "copula"] = ("seen" if state == "seen" else "held" if state == "held" else reach, "other", 1.0)
        arcs[state, "target"] = ("seen", "claim" if state == "held" else "other", 1.0)
        arcs[state, "report"] = ("none", "other", 1.0)
        arcs[state, "boundary"] = ("none", "boundary", 1.0)
        for told in ("", "told "):
            arcs[state, f"{told}insult"] = (state, f"{told}aimed", 1.0) if state == "seen" or copula else ("held", f"{told}held", 1.0)
            arcs[state, f"{told}threat"] = (later, f"{told}threat", boost if state == "seen" else 1.0)
    return Transducer("none", arcs)


def grammar() -> Transducer:
    told = ("told insult", "told harm", "threat", "told threat")
    return negation().then(reported(), CLASSES).then(threat(), CLASSES).then(target(), (*CLASSES, *told))


class Trie:
    """The lexical transducer: whole words by class, and weighted beginnings for insults."""

    def __init__(self, stems: dict[str, float], prior: float = 3.0):
        self.whole = {w: (c, prior) for c, ws in SEEDS.items() for w in ws.split()}
        self.root: dict = {}
        for stem, weight in stems.items():
            node = self.root
            for ch in stem:
                node = node.setdefault(ch, {})
            node["weight"] = weight

    def read(self, token: str) -> tuple[str, float]:
        if token in _PUNCTUATION:
            return _PUNCTUATION[token], 0.0
        node, best = self.root, 0.0
        for ch in token:
            if (node := node.get(ch)) is None:
                break
            best = max(best, node.get("weight", 0.0))
        if best > 0:
            return "insult", best
        return self.whole.get(token, ("other", 0.0))


@dataclass
class ToxicModel:
    stems: dict[str, float] = field(default_factory=dict)
    weights: dict[str, float] = field(default_factory=lambda: dict(PRIOR))

    def matches(self, text: str) -> Iterator[tuple[str, float]]:
        """(pattern, weight) of what fires, clause by clause."""
        if not hasattr(self, "_read"):
            self._read, self._machine = Interned(Trie(self.stems).read, 80_000), grammar()
        tokens = _TOKEN(text.lower())
        classes = list(map(self._read.__getitem__, tokens))
        if not any(c in ("insult", "harm") for c, _ in classes):
            return
        state, arcs, before, held = self._machine.start, self._machine.arcs, None, []
        for word, (symbol, weight) in zip(tokens, classes, strict=True):
            state, written, factor = arcs[state, symbol]
            if written == "claim":
                yield from (("told" if told else "aimed", w) for told, w in held)
                held = []
            elif written == "boundary":
                held = []
            elif written != "other" and (told := written.startswith("told")) is not None:
                kind = written.removeprefix("told ")
                if kind != "threat" and before not in (None, word):
                    kind = "piled" if kind == "held" else kind
                if kind == "held":
                    held.append((told, factor * weight))
                else:
                    yield "told" if told else kind, factor * weight
                before = word if written != "threat" else before

    def measures(self, text: str | None) -> dict[str, float]:
        found = dict.fromkeys(PRIOR, 0.0)
        for kind, weight in self.matches(text or ""):
            found[kind] += weight
        return {k: math.log1p(v) for k, v in found.items()}

    def score(self, text: str | None) -> float:
        x = self.measures(text)
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, NO_MATCH + sum(self.weights[k] * v for k, v in x.items())))))

    def __getstate__(self):
        return {"stems": self.stems, "weights": self.weights}


def _beginnings(text: str) -> Counter:
    """Beginnings of the text's distinct words, with how many words share each."""
    out: Counter = Counter()
    for w in set(_TOKEN(text.lower())):
        for n in range(4, min(12, len(w)) + 1):
            out[w[:n]] += 1
    return out


def _sample(docs: DataFrame, labels: DataFrame, allowed: Column, positives: int, negatives: int) -> DataFrame:
    marks = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).filter("toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    rows = docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text"), allowed.alias("may")).filter("may and text is not null")
    held = {r["toxic"]: r["n"] for r in rows.select("doc_id").join(marks, "doc_id").groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    share = {y: int(min(1.0, most / max(1, held.get(y, 0))) * (1 << 32)) for y, most in ((1, positives), (0, negatives))}
    limit = F.when(F.col("toxic") == 1, F.lit(share[1])).otherwise(F.lit(share[0]))
    return rows.join(marks, "doc_id").filter(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 32)) < limit).select("toxic", "text")


def _texts(batches: Iterator[pa.RecordBatch], column: int = 1) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """The batches in parts of a few megabytes, with the texts of each."""
    for batch in batches:
        for a, b, texts in runs(batch.column(column), 1 << 20):
            yield batch.slice(a, b - a), [(t or b"").decode("utf-8", "replace") for t in texts]


def _leading_run(text: str, k: int = 5) -> int:
    """The least hash of k adjacent words: near copies mostly share it, other texts don't."""
    tokens = _TOKEN(text.lower())
    return min((xxhash.xxh3_64_intdigest(" ".join(tokens[i : i + k])) for i in range(max(1, len(tokens) - k + 1))), default=0) >> 1


def _without_copies(sample: DataFrame) -> DataFrame:
    """One row of most groups of toxic near copies, so that a group's own words don't look telling."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in _texts(batches):
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array([_leading_run(t) for t in texts], pa.int64())], names=["toxic", "text", "lead"])

    led = sample.filter("toxic = 1").mapInArrow(run, "toxic int, text string, lead long")
    kept = led.groupBy("toxic", "lead").agg(F.min("text").alias("text")).select("toxic", "text")
    return kept.union(sample.filter("toxic = 0").select("toxic", "text"))


def fit(
    docs: DataFrame, labels: DataFrame, allowed: Column, positives: int = 2500, negatives: int = 5000, least_share: float = 0.025, work=None
) -> ToxicModel:
    """Learn the insult arcs and the logistic from a bounded sample of the allowed labelled rows. An
    arc must explain `least_share` of the toxic sample and five rows, so that wrong labels teach none."""
    sample = _without_copies(_sample(docs, labels, allowed, positives, negatives))
    sample = work.table(sample, "labelled") if work else sample

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list[int]] = {}

        def flush() -> pa.RecordBatch:
            columns = list(zip(*held.values(), strict=True))
            return pa.RecordBatch.from_arrays([pa.array(list(held)), *(pa.array(c, pa.int64()) for c in columns)], names=["stem", "pos", "neg", "words"])

        for part, texts in _texts(batches):
            for y, text in zip(part.column(0).to_pylist(), texts, strict=True):
                for stem, k in [*_beginnings(text).items(), ("", 0)]:
                    row = held.setdefault(stem, [0, 0, 0])
                    row[0 if y else 1] += 1
                    row[2] += k if y else 0
                if len(held) > 100_000:  # sums meet again in the shuffle
                    yield flush()
                    held = {}
        if held:
            yield flush()

    counted = sample.mapInArrow(count, "stem string, pos long, neg long, words long").groupBy("stem").agg(*(F.sum(c).alias(c) for c in ("pos", "neg", "words")))
    totals = counted.filter("stem = ''").first()
    if totals is None or not totals["pos"] or not totals["neg"]:
        return ToxicModel()
    n_pos, n_neg = totals["pos"], totals["neg"]
    support = max(5, int(least_share * n_pos))
    telling = {
        r["stem"]: (r["pos"], r["neg"], r["words"])
        for r in counted.filter(f"stem <> '' and pos >= {support} and 20 * (neg + 0.5) * {n_pos + 1} < (pos + 0.5) * {n_neg + 1}").collect()
    }

    def marks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, texts in _texts(batches):
            found = [[s for s in _beginnings(t) if s in telling] for t in texts]
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.list_(pa.string()))], names=["stems"])

    open_ = [set(r["stems"]) for r in sample.filter("toxic = 1").mapInArrow(marks, "stems array<string>").collect()]
    stems: dict[str, float] = {}
    while True:
        gain = Counter(s for d in open_ for s in d)
        best = max(gain, key=lambda s: (gain[s] - 10 * telling[s][1], telling[s][2], len(s), s), default=None)
        if best is None or gain[best] < support or gain[best] <= 10 * telling[best][1]:
            break
        stems[best] = math.log((telling[best][0] + 0.5) / (n_pos + 1)) - math.log((telling[best][1] + 0.5) / (n_neg + 1))
        open_ = [d for d in open_ if best not in d]
    # words that share a chosen one's strength but always stand beside others
    for s, (pos, neg, words) in telling.items():
        if neg == 0 and pos >= 0.05 * n_pos and not any(s.startswith(x) or x.startswith(s) for x in stems):
            longer = max((x for x in telling if x.startswith(s) and telling[x][2] == words), key=len)
            stems[longer] = math.log((pos + 0.5) / (n_pos + 1)) - math.log(0.5 / (n_neg + 1))
    model, kinds = ToxicModel(stems), list(PRIOR)

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in _texts(batches):
            found = [model.measures(t) for t in texts]
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array([m[k] for m in found], pa.float64()) for k in kinds)], names=["toxic", *kinds])

    rows = sample.mapInArrow(measured, "toxic int, " + ", ".join(f"{k} double" for k in kinds)).toArrow()
    return ToxicModel(stems, _weights(np.column_stack([rows[k].to_numpy() for k in kinds]), rows["toxic"].to_numpy()))


def _weights(x: np.ndarray, y: np.ndarray, ridge: float = 1.0) -> dict[str, float]:
    """Logistic weights drawn to PRIOR, at least half of it; a told match counts less than a direct one."""
    prior = np.array(list(PRIOR.values()))
    order = np.lexsort((y, *x.T))
    x, y, w = x[order], y[order], prior.copy()
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(NO_MATCH + x @ w, -30, 30)))
        move = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w)), x.T @ (p - y) + ridge * (w - prior))
        w = w - np.clip(move, -2, 2)
        if np.abs(move).max() < 1e-8:
            break
    out = dict(zip(PRIOR, np.maximum(w, prior / 2).tolist(), strict=True))
    return out | {"told": min(out["told"], 0.6 * min(out["aimed"], out["piled"], out["threat"]))}


def score(docs: DataFrame, model: ToxicModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and score of every row; the label of a row is never read."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in runs(batch.column(1)):
                scores = [sent.value.score(t.decode("utf-8", "replace") if t else None) for t in texts]
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], pa.array(scores, pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")


def without_toxic(docs: DataFrame, model: ToxicModel, text_col: str = "text", limit: float = 0.5) -> DataFrame:
    """The documents that score below the limit, with all their columns."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    return keep_rows(docs, text_col, lambda texts: [sent.value.score(t.decode("utf-8", "replace") if t else None) < limit for t in texts])
