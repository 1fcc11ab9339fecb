"""Every operator against brute force, and on null, empty, long, repeated and clashing input."""

import json
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
import zstandard
from pyspark.sql import functions as F

from cellbalance.llm import bpe, chat, fmindex, langid, licenses, neardup, quality, sharding, toxicity, warc
from cellbalance.llm.common import Work, table

DOCS = "doc_id long, text string, lang string, source string, n_chars long, key string, n int, comp string, spans string, shard string, size string"
WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def rows_of(texts):
    return [(i, t, "en", "s", None, "k", 1, "c", "x", "y", "z") for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def odd(spark):
    """Null, empty, blank, one word, very long, repeated, and a null id; columns with clashing names."""
    long = " ".join(f"w{i % 997}" for i in range(40_000))
    texts = [None, "", " \n\t", "one", "a b c d e f g h", long, long + " tail", "the cat sat on the mat " * 8, "the cat sat on the mat " * 8, "1234 !! 56", "You are not an idiot, said Bob."]
    rows = [*rows_of(texts), (None, "no id here at all", None, None, None, None, None, None, None, None, None), rows_of(texts)[7]]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def docs(spark, data):
    return table(spark, data, "documents")


def labels_of(spark, pairs):
    return spark.createDataFrame(pairs, "doc_id long, quality int, toxic int")


def brute_components(rows, k):
    def shingles(text):
        w = (text or "").translate(LOW)
        w = re.findall(r"[^\x20\x09-\x0D]+", w)
        return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())

    sets = {r.doc_id: shingles(r.text) for r in rows}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                a2, b2 = find(a), find(b)
                root[max(a2, b2)] = min(a2, b2)
    return {i: find(i) for i in ids}, {i: len(s) for i, s in sets.items()}


def test_near_duplicates_match_brute_force(spark, docs):
    rng = random.Random(1)
    base = [f"t{rng.randrange(400)}" for _ in range(120)]
    extra = []
    for i in range(60):  # one crowd of near copies: some pairs above the threshold, most below
        w = list(base)
        for _ in range(rng.randrange(2, 24)):
            w[rng.randrange(len(w))] = f"e{rng.randrange(10_000)}"
        extra.append((100_000 + i, " ".join(w)))
    some = docs.select("doc_id", "text").union(spark.createDataFrame(extra, "doc_id long, text string"))
    for limit in (24, 3):
        got = {r.doc_id: r for r in neardup.near_duplicates(some, shingle=2, bucket_limit=limit).collect()}
        want, sizes = brute_components(some.collect(), 2)
        assert {i: r.component_id for i, r in got.items()} == want
        assert {i: r.n_shingles for i, r in got.items()} == sizes
        assert all(r.kept == (r.component_id == r.doc_id) for r in got.values())


def test_near_duplicates_on_odd_rows(spark, odd):
    got = neardup.near_duplicates(odd, shingle=5).collect()
    by = {r.doc_id: r for r in got if r.doc_id is not None}
    assert len(got) == 13 and all(by[i].n_shingles == 0 and by[i].kept for i in (0, 1, 2))
    assert by[6].component_id == 5 and by[8].component_id == 7 and not by[8].kept
    assert [r.component_id for r in got if r.doc_id is None] == [None]
    kept = neardup.one_of_each(odd).collect()
    assert Counter(r.doc_id for r in kept)[7] == 1 and 8 not in {r.doc_id for r in kept} and kept[0].asDict().keys() == dict(odd.dtypes).keys()
    assert neardup.near_duplicates(odd.limit(0)).count() == 0


def brute_contamination(text, items, window=13):
    w, hit, found = WORDS.findall((text or "").translate(LOW)), set(), set()
    for name, item in items:
        iw = WORDS.findall((item or "").translate(LOW))
        for i in range(max(1, len(iw) - window + 1) if iw else 0):
            piece = iw[i : i + window]
            for a in range(len(w) - len(piece) + 1):
                if w[a : a + len(piece)] == piece:
                    hit |= set(range(a, a + len(piece)))
                    found.add(name)
    return len(w), len(hit), sorted(found)


def test_contamination_matches_brute_force(spark, docs, odd, data):
    items = [(str(r.item_id), r.text) for r in table(spark, data, "benchmark").collect()] + [("short", "The CAT sat"), (None, "!!"), ("z", None), ("copy", "the cat sat")]
    bench = spark.createDataFrame(items, "item_id string, text string")
    for rows, blocks in ((docs.limit(60).select("doc_id", "text"), 32 << 20), (odd, 32 << 20), (odd, 2000)):
        got = sorted((r.doc_id or -1, r.n_words, r.n_hit, tuple(r["items"])) for r in fmindex.contamination(rows, bench, block_bytes=blocks).collect())
        want = sorted((r.doc_id or -1, *(lambda x: (x[0], x[1], tuple(x[2])))(brute_contamination(r.text, items))) for r in rows.collect())
        assert got == want
    assert fmindex.contamination(odd, bench.limit(0)).agg(F.sum("n_hit")).first()[0] == 0
    assert fmindex.contamination(odd.limit(0), bench).count() == 0
    assert {r.doc_id for r in odd.collect()} - {r.doc_id for r in fmindex.decontaminated(odd, bench).collect()} == {7, 8}
    assert fmindex.without_spans("Ab, cd EF gh!", [(1, 3)]) == "Ab,  gh!"


def test_wavelet_ranks_and_located_rows():
    rng = np.random.default_rng(5)
    text = np.append(rng.integers(0, 4, 600), 0).astype(np.int32)
    index = fmindex.FMIndex(text, 2)
    assert sorted(fmindex.suffix_order(text, 2).tolist()) == list(range(len(text)))
    for i in (0, 63, 64, 65, 300, 601):
        for c in range(4):
            assert index.tree.rank(np.array([c]), np.array([i]))[0] == (index.bwt[:i] == c).sum()
    pattern = np.array([1, 2, 3])
    _, low, high = index.search(pattern[None], np.array([3]))
    at = index.locate(np.arange(low[0], high[0])) if len(low) else np.zeros(0)
    assert sorted(at.tolist()) == [i for i in range(len(text) - 2) if (text[i : i + 3] == pattern).all()]


def test_shards_are_even_and_slots_gapless(spark, docs, odd):
    hot = spark.range(3000).select((F.col("id") + 50_000).alias("doc_id"), F.lit("same text").alias("text"))
    for rows in (docs.select("doc_id", "text").union(hot), odd.select("doc_id", "text"), odd.limit(0)):
        got, text = sharding.document_shards(rows).collect(), defaultdict(set)
        for r in rows.collect():
            text[r.doc_id].add((len((r.text or "").encode()) + 1, zlib.crc32((r.text or "").encode())))
        slots, size = defaultdict(list), Counter()
        for r in got:
            assert (r.size, r.text_crc32) in text[r.doc_id]
            slots[r.shard].append(r.slot)
            size[r.shard] += r.size
        assert len(got) == rows.count() and all(sorted(s) == list(range(len(s))) for s in slots.values())
        if len(got) > 1000:
            assert max(size.values()) - min(size[k] for k in range(16)) <= 2 * max(r.size for r in got)


def test_sharding_runs_no_python(spark, docs):
    plan = sharding.document_shards(docs)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_warc_derivatives(spark, data):
    pages = spark.createDataFrame(
        [(1, "http://a.org/x/", '<html lang="fr"><title>T &amp; t</title><script>no()</script><p>One<br>two <a href="../y?q=1#z">l</a><!-- c --></p>'), (2, None, None), (3, "http://b.org", ""), (3, "http://b.org", ""), (4, "::", "<a href='http://[bad'>x</a><p")],
        "page_id long, url string, html string",
    )
    got = warc.derivatives(warc.page_responses(pages), "page_id").collect()
    assert len(got) == 10
    meta = next(r for r in got if r.page_id == 1 and r.record_type == "metadata")
    conv = next(r for r in got if r.page_id == 1 and r.record_type == "conversion")
    assert bytes(meta.block).decode() == "http-status: HTTP/1.1 200 OK\r\nhttp-header: Content-Type: text/html; charset=utf-8\r\ntitle: T & t\r\nlanguage: fr\r\noutlink: http://a.org/y?q=1#z a/@href\r\n"
    assert bytes(conv.block).decode() == "One\ntwo l" and conv.refers_to == meta.refers_to and f"WARC-Concurrent-To: {conv.record_id}" in meta.headers
    html = pages.filter("page_id = 1").first().html.encode()
    assert f"WARC-Source-Payload-Digest: {warc.digest(html)}" in conv.headers and "Content-Type: text/html" in conv.headers
    assert all(r.content_length == len(r.block) and r.block_digest == warc.digest(bytes(r.block)) for r in got)
    whole = warc.derivatives(warc.page_responses(table(spark, data, "pages")), "page_id")
    assert whole.count() == 2 * table(spark, data, "pages").count() and warc.derivatives(warc.page_responses(pages.limit(0)), "page_id").count() == 0
    raw = warc.serialised({"headers": conv.headers, "block": bytes(conv.block)}, member=False)
    assert raw.startswith(b"WARC/1.1\r\nWARC-Type: conversion") and raw.endswith(b"two l\r\n\r\n")
    members = warc.warc_members(warc.derivatives(warc.page_responses(pages), "page_id")).collect()
    back = list(warc.read_members(b"".join(bytes(r.member) for r in members)))
    assert [(h["WARC-Record-ID"], h.get("WARC-Refers-To"), b) for h, b in back] == [(r.record_id, r.refers_to, bytes(r.block)) for r in members]
    assert ["".join(f"{k}: {v}\r\n" for k, v in h.items()) for h, _ in back] == [r.headers for r in members]


def test_warc_keeps_all_source_headers_and_tells_responses_apart(spark):
    http = "HTTP/1.1 301 Moved\r\nDate: Mon, 01 Jan 2024 00:00:00 GMT\r\nETag: \"x; y\"\r\nServer: s\r\n  folded\r\nLocation: http://c.org/\r\nContent-Encoding: gzip\r\n\r\n"
    long = "<p>" + "word " * 200_000
    rows = [(None, None, "http://a.org", http, b"<p>x", "k"), (None, None, "http://b.org", http, b"<p>x", "k"), (None, None, "http://a.org", http, b"<p>y", "k"), ("<urn:uuid:1>", "2024-01-01T00:00:00Z", None, None, long.encode(), "k")]
    responses = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "page_id long, record_id string, date string, target_uri string, http_headers string, payload binary, headers string")
    got = warc.derivatives(responses.withColumn("payload_digest", F.lit(None).cast("string")), "page_id").collect()
    assert len({r.record_id for r in got}) == len(got) == 8
    kept = json.loads(next(x for x in got[1].headers.split("\r\n") if x.startswith("WARC-Source-Headers: "))[21:])
    assert kept == ["HTTP/1.1 301 Moved", "Date: Mon, 01 Jan 2024 00:00:00 GMT", 'ETag: "x; y"', "Server: s folded", "Location: http://c.org/", "Content-Encoding: gzip"]
    assert [x.split(": ", 1)[1] for x in bytes(got[0].block).decode().splitlines()] == kept
    assert bytes(got[7].block).decode() == " ".join(["word"] * 200_000) and got[7].refers_to == "<urn:uuid:1>" and "Source-Headers" not in got[7].headers


def test_toxicity_grammar_scores_clauses():
    model = toxicity.ToxicModel({"grumb": 4.0})
    found = lambda text: sorted(k for k, _ in model.matches(text))
    # an insult aimed at nobody is a word by itself
    for text in ("grumbler", "the word grumbler appears here", "The clown performed at the party.", "a clown, another clown and one more clown", "they kill time", "You came. A grumbler came."):
        assert found(text) == [] and model.score(text) == model.score(None) == model.score("") == model.score("plain words") < 0.5
    for text in ("you grumbler", "he is a grumbler", "such a grumbler she is", "Sie ist ein Trottel", "eres un idiota"):
        assert found(text) == ["aimed"] and model.score(text) >= 0.5, text
    assert found("grumbler and idiot") == ["piled"] and found("I will kill you") == ["threat"] and model.score("I will kill you") >= 0.5
    assert found('they said "grumbler"') == [] and found('she said you are a grumbler') == ["told"] == found('"you are a grumbler", she wrote')
    assert model.score("you are a grumbler") > model.score("she said you are a grumbler") > model.score("she said nothing")
    assert model.score("you are a grumbler") > 0.5 > model.score("you are not a grumbler") > model.score("you are not here")


def test_toxicity_reads_allowed_labels_only(spark):
    rng = random.Random(4)
    words = lambda i: " ".join(f"{rng.choice('bcdfg')}{rng.choice('aeiou')}{rng.choice('lmnrst')}{rng.randrange(90)}x" for _ in range(30)) + (" zorking zorkish" if i % 3 == 0 else "")
    docs = spark.createDataFrame([(i, words(i)) for i in range(600)], "doc_id long, text string")
    allowed = F.col("doc_id") < 400
    told = [(i, 0, int(i % 3 == 0)) for i in range(400)]
    models = [toxicity.fit(docs, labels_of(spark, told + [(i, 0, y) for i in range(400, 600)]), allowed, positives=60, negatives=90) for y in (0, 1)]
    assert models[0] == models[1] and models[0].stems
    clash = labels_of(spark, told + [(i, 0, 0) for i in range(400)])  # a second label that says no
    assert toxicity.fit(docs, clash, allowed) == toxicity.fit(docs, labels_of(spark, told), allowed)


def test_toxicity_learns_stems_and_holds_out(spark, docs, odd):
    rng = random.Random(3)
    rows = []
    for i in range(400):
        w = [f"{rng.choice('bcdfg')}{rng.choice('aeiou')}{rng.choice('lmnrst')}{rng.choice('aeiou')}{rng.choice('bcdfglmnrst')}x" for _ in range(40)]
        if i % 4 == 0:
            for at, word in zip(rng.sample(range(40), 2), rng.sample(["zorkish", "zorking", "zorkly", "quibfoul"], 2), strict=True):
                w[at] = word
        rows.append((i, " ".join(w), int(i % 4 == 0)))
    known = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    model = toxicity.fit(known.select("doc_id", "text"), known.select("doc_id", "toxic"), F.col("doc_id") % 5 != 0)
    got = {r.doc_id: r.score >= 0.5 for r in toxicity.score(known, model).collect()}
    assert all(got[i] == bool(y) for i, _, y in rows)
    assert toxicity.fit(odd, labels_of(spark, []), F.lit(True)) == toxicity.ToxicModel()
    assert toxicity.score(odd, model).count() == 13 and toxicity.without_toxic(odd, model).columns == odd.columns


def test_bpe_agrees_with_the_library(spark, docs, odd):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    reference = Tokenizer.from_file(path)
    reference.no_truncation()
    reference.no_padding()
    odd_texts = spark.createDataFrame([(900 + i, t) for i, t in enumerate(["a" * 700, "x<|endoftext|> y", "    end  ", "é中😀 ́", "don't  we'll\n\n x", "½²Ⅷ"])], "doc_id long, text string")
    rows = docs.select("doc_id", "text").union(odd.select("doc_id", "text")).union(odd_texts)
    got = Counter((r.doc_id, r.n_tokens, bytes(r.ids), r.decoded) for r in bpe.round_trip(rows, path).collect())
    want = Counter()
    for r in rows.collect():
        ids = reference.encode(r.text or "", add_special_tokens=False).ids
        want[(r.doc_id, len(ids), np.array(ids, "<u4").tobytes(), reference.decode(ids, skip_special_tokens=False))] += 1
    assert got == want
    two = Counter((r.doc_id, r.n_tokens, bytes(r.ids), r.decoded) for r in bpe.decode(bpe.encode(odd, path), path).collect())
    assert two == Counter((r.doc_id, r.n_tokens, bytes(r.ids), r.decoded) for r in bpe.round_trip(odd, path).collect())
    one = bpe.RankArrayBPE(open(path, "rb").read())
    assert all(one.encode_words([w.encode()])[0] == np.array(one.word(w.encode()), "<u4").tobytes() for w in ("hello", " world", "z" * 64, "z" * 65))


def test_quality_counts_match_brute_force(spark, docs, odd):
    press = zstandard.ZstdCompressor(level=3, write_checksum=False).compress
    for rows in (docs.select("doc_id", "text"), odd):
        texts = Counter(r.text for r in rows.collect())
        for r in quality.compression_bands(rows).join(rows.select("doc_id", "text"), "doc_id").dropDuplicates(["doc_id"]).collect():
            text = r.text or ""
            w = re.findall(r"[^\x20\x09-\x0D]+", text)
            places = defaultdict(list)
            for i in range(len(w) - 7):
                places[tuple(w[i : i + 8])].append(i)
            covered = {j for at in places.values() if len(at) > 1 for i in at for j in range(i, i + 8)}
            lines, seen, again = text.split("\n"), set(), 0
            for line in lines:
                if re.search(r"[^\x20\x09-\x0D]", line):
                    again += line in seen
                    seen.add(line)
            assert (r.n_words, r.word_chars, r.n_symbols) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)))
            assert (r.n_dup_lines, r.n_repeat_words) == (again, len(covered))
            assert r.base_failed == (len(w) < 20 or 100 * len(covered) > 30 * len(w)) and (not r.kept or not r.base_failed)
            raw = text.encode()
            assert not raw or abs(r.ratio - len(raw) / max(1, len(press(raw)) - quality.FRAME)) < 1e-9
        assert sum(texts.values()) == rows.count()
    assert quality.compression_bands(odd.limit(0)).count() == 0


def test_license_base_places_and_suppression(spark, docs, odd):
    scanner = licenses.Scanner(licenses.rules())
    assert len({r.pattern for r, _ in scanner.rules}) == len(scanner.rules) > 200
    for r in docs.collect() + odd.collect():
        w, places = WORDS.findall((r.text or "").translate(LOW)), []
        for phrase, _ in licenses.BASE:
            p = phrase.split()
            places += [i for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
        got = licenses.scan_text(r.text.encode() if r.text else None, scanner)
        assert (got["n_words"], got["n_base"], got["first_word"], got["last_word"]) == (len(w), len(places), min(places, default=None), max(places, default=None))
        assert set(got["base_labels"]) <= set(got["labels"])
    found = licenses.scan_text(b"Licensed under the GNU Lesser General Public License, version 2.1 or later. MIT License MIT license", scanner)
    assert found["labels"] == ["lgpl", "lgpl-2.1", "mit"] and found["n_base"] == 2 and sorted(d["label"] for d in found["detections"]) == ["lgpl", "lgpl-2.1", "mit", "mit", "mit"]
    assert licenses.scan(odd).count() == 13 and licenses.scan(odd.limit(0)).count() == 0


def sample_of(tree, least):
    """A text that a parsed pattern matches: first branches and fewest repeats, or last branches and one repeat."""
    out = []
    for op, arg in tree:
        name = str(op)
        if name == "LITERAL":
            out.append(chr(arg))
        elif name == "ANY":
            out.append("z")
        elif name == "IN":
            out.append(chr(arg[0][1] if str(arg[0][0]) == "LITERAL" else arg[0][1][0]))
        elif name in ("MAX_REPEAT", "MIN_REPEAT"):
            out += [sample_of(arg[2], least)] * max(arg[0], 0 if least else min(arg[1], 1))
        elif name == "SUBPATTERN":
            out.append(sample_of(arg[3], least))
        elif name == "BRANCH":
            out.append(sample_of(arg[1][0 if least else -1], least))
        else:
            raise ValueError(name)
    return "".join(out)


def test_every_license_signature_detects_its_own_wording():
    from re import _parser

    table = licenses.rules()
    scanner = licenses.Scanner(table)
    for rule in table:
        for least in (True, False):
            text = sample_of(_parser.parse(rule.pattern), least)
            assert f" {rule.keyword} " in f" {text} " and re.fullmatch(rule.pattern, text), rule
            found = licenses.scan_text(f"See here: {text}. The end".encode(), scanner)
            inside = [d for d in found["detections"] if d["label"] == rule.label or d["priority"] >= rule.priority]
            assert inside, rule  # itself, or a signature that outranks it
            alone = licenses.Scanner([rule]).detections(f" see here {text} the end ")
            assert [r.label for _, _, r in alone] == [rule.label], rule


def brute_scan(text, table):
    """Accepted detections, each found on its own and compared with every one accepted before."""
    words = WORDS.findall((text or "").translate(LOW))
    normal = " " + " ".join(words) + " "
    found = [(m.start(1), m.end(1), i) for i, r in enumerate(table) for m in re.finditer(f"(?<= )({r.pattern})(?= )", normal)]
    kept = []
    for a, b, i in sorted(found, key=lambda d: (-table[d[2]].priority, d[0] - d[1], d[0], d[2])):
        if not any(x <= a and b <= y for x, y, _ in kept):
            kept.append((a, b, i))
    return {table[i].label for _, _, i in kept}, max([0, *(table[i].reliability for _, _, i in kept)])


def test_license_labels_and_scores_match_brute_force(docs):
    table_ = licenses.rules()
    scanner, rng = licenses.Scanner(table_), random.Random(2)
    from re import _parser

    pieces = [sample_of(_parser.parse(r.pattern), True) for r in table_]
    texts = [" and ".join(rng.sample(pieces, 5)) for _ in range(60)] + [r.text for r in docs.limit(60).collect()] + [None, "", "gnu general public license " * 3000]
    for text in texts:
        got, (labels, score) = licenses.scan_text(text.encode() if text else None, scanner), brute_scan(text, table_) if text != texts[-1] else ({"gpl"}, 0.6)
        assert got["labels"] == sorted(labels | set(got["base_labels"])) and got["score"] == max(score, 0.6 * bool(got["n_base"]))


def test_quality_bands_and_chunks_match_brute_force(spark):
    press = zstandard.ZstdCompressor(level=3, write_checksum=False).compress
    rng = random.Random(6)
    prose = lambda n: " ".join(rng.choice(["river", "stone", "walks", "under", "green", "light", "seven", "quiet"]) + str(rng.randrange(500)) for _ in range(n))
    noise = lambda n: "".join(chr(rng.randrange(1, 128)) for _ in range(n))
    texts = ["", "a", prose(30), prose(600), prose(700) + " " + noise(4000), prose(3000), prose(3000) + " " + noise(16000), "x " * 3000, noise(300), prose(500)[:4096], prose(500)[:4097], noise(5000)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in quality.compression_bands(docs).collect():
        raw = texts[r.doc_id].encode()
        chunks = [raw[a : a + 4096] for a in range(0, len(raw), 4096)] if len(raw) > 4096 else []

        def inside(block):
            low, high = next((a, b) for most, a, b in quality.BANDS if len(block) <= most)
            return low <= len(block) / max(1, len(press(block)) - 9) <= high

        bad = sum(not inside(c) for c in chunks)
        assert (r.n_chunks, r.bad_chunks) == (len(chunks), bad)
        assert r.in_band == (bool(raw) and inside(raw) and bad <= 0.25 * len(chunks)) and r.kept == (r.in_band and not r.base_failed)
    half = {r.doc_id: r.bad_chunks for r in quality.compression_bands(docs).collect()}
    assert half[4] >= 1 and half[6] >= 3  # noise in a text of two chunks, and in a last chunk


def test_rows_that_share_an_id_are_judged_apart(spark):
    a, b, c = (" ".join(f"{x}{i}" for i in range(60)) for x in "abc")
    rows = [(1, a, "x"), (1, b, "y"), (2, a + " a61", "z"), (3, b, "u"), (None, c, "v"), (None, c, "v"), (None, b, "w"), (4, a, "p"), (4, a, "q"), (5, None, "n"), (5, None, "n"), (6, c + " end", "m")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = [tuple(r) for r in neardup.one_of_each(docs).collect()]
    assert sorted((r[0] or 0, r[1] or "") for r in got) == sorted([(1, a), (1, b), (5, ""), (5, ""), (0, c)] if (None, c, "v") in got else [(1, a), (1, b), (5, ""), (5, ""), (6, c + " end")])
    only = spark.createDataFrame([(4, a, "p"), (4, a, "q"), (4, a, "q")], docs.schema)
    assert len({tuple(r) for _ in range(3) for r in neardup.one_of_each(only).collect()}) == 1 == neardup.one_of_each(only).count()
    by = {(r.doc_id, r.component_id) for r in neardup.near_duplicates(docs, shingle=5).collect()}
    assert {(1, 1), (2, 1), (3, 1), (4, 1), (6, 6), (None, None)} <= by


def test_hot_keys_are_dealt_out(spark):
    pairs = spark.range(1000).selectExpr("id + 10 as a", "cast(1 as long) as b")
    sets = spark.range(1100).selectExpr("id as cid", "array(id) as shingles")
    hot = spark.createDataFrame([(1, 15)], "b long, last int")
    dealt = neardup._dealt(pairs, hot, "b", "a", sets.select(F.col("cid").alias("b"), "shingles"))
    assert dealt.count() == 1000 and dealt.select("a").distinct().count() == 1000
    work = Work(spark)
    assert neardup._similar(work, work.table(pairs, "pairs"), sets.withColumn("shingles", F.array(F.lit(1))), 80).count() == 1000


def test_a_crowd_is_linked_whichever_text_comes_first(spark):
    # copies of one text with edits of their own; the text itself comes last, and no two copies are alike enough
    rng = random.Random(12)
    base = [f"t{i}" for i in range(150)]
    rows = []
    for i in range(80):
        w = list(base)
        for at in rng.sample(range(150), 4):
            w[at] = f"e{i}x{at}"
        rows.append((i, " ".join(w)))
    docs = spark.createDataFrame([*rows, (500, " ".join(base))], "doc_id long, text string")
    got = neardup.near_duplicates(docs, shingle=5).collect()
    want, _ = brute_components(docs.collect(), 5)
    assert {r.doc_id: r.component_id for r in got} == want


def test_long_texts_are_searched_in_pieces():
    items = [("x", " ".join(f"b{i}" for i in range(30))), ("short", "b3 b4")]
    phrases = fmindex.Phrases(items, 13)
    text = " ".join(["filler"] * 500 + [f"b{i}" for i in range(30)] + ["filler"] * 500 + [f"b{i}" for i in range(13)]).encode()
    whole = fmindex.scan_texts([text, None, b"b3 b4"], [phrases], 13, 1 << 20)
    assert whole == ([1043, 0, 2], [[(500, 530), (1030, 1043)], [], [(0, 2)]], [{"x", "short"}, set(), {"short"}])
    for most in (40, 100, 333, 2000):
        assert fmindex.scan_texts([text, None, b"b3 b4"], [phrases], 13, most) == whole


def test_spans_are_taken_out_of_texts(spark):
    bench = spark.createDataFrame([(k, " ".join(f"b{k}x{i}" for i in range(20))) for k in range(40)], "item_id long, text string")
    item = bench.filter("item_id = 7").first().text
    docs = spark.createDataFrame([(1, f"Keep this, {item}; and THIS.", "s"), (2, None, "t"), (2, "", "u"), (None, "clean", "v")], "doc_id long, text string, spans string")
    for sizes in ({}, {"block_bytes": 2000}, {"block_bytes": 1000, "pass_bytes": 3000}):
        got = sorted(((r.text or "", r.spans) for r in fmindex.cleaned(docs, bench, **sizes).collect()))
        assert got == [("", "t"), ("", "u"), ("Keep this, ; and THIS.", "s"), ("clean", "v")]
        assert sorted(r.spans for r in fmindex.decontaminated(docs, bench, **sizes).collect()) == ["t", "u", "v"]


def plain_shards(rows, shards=16, tolerance=0.001, share=32):
    """Histogram sort on one list of (key, size): refine the bins, then deal bins by their middle."""
    total, shift, leaves = sum(s for _, s in rows), 52, []

    def count(rows, shift):
        held = defaultdict(lambda: [0, 0])
        for k, s in rows:
            held[k >> shift][0] += s
            held[k >> shift][1] += 1
        return [(b, shift, *v) for b, v in held.items()]

    fresh = count(rows, shift)
    while True:
        leaves = sorted([*leaves, *fresh], key=lambda b: b[0] << b[1])
        before, cut = 0, []
        for b in leaves:
            first, last = before * shards // total, (before + b[2]) * shards // total
            before += b[2]
            if b[1] == shift and shift > 0 and b[3] > 1 and (b[2] * shards * share > total or first < last and b[2] > tolerance * total / shards):
                cut.append(b)
        if not cut:
            break
        gone, finer = {b[0] for b in cut}, max(0, shift - 8)
        leaves = [b for b in leaves if b not in cut]
        fresh = count([r for r in rows if r[0] >> shift in gone], finer)
        shift = finer
    out, before = {}, 0
    for b in leaves:
        out[b[0], b[1]] = min(shards - 1, (2 * before + b[2]) * shards // (2 * total))
        before += b[2]
    return out


def test_shards_match_a_plain_histogram_sort(spark, docs):
    keyed = docs.select("doc_id", (F.octet_length(F.coalesce("text", F.lit(""))) + 1).alias("size"), F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("text_crc32"))
    rows = keyed.withColumn("key", sharding.text_order()).collect()
    bins = plain_shards([(r.key, r.size) for r in rows])
    want = {r.doc_id: next(s for (b, shift), s in bins.items() if r.key >> shift == b) for r in rows}
    got = sharding.document_shards(docs).collect()
    assert {r.doc_id: r.shard for r in got} == want
    order = sorted(rows, key=lambda r: (r.key, r.doc_id))
    nth, slots = Counter(), {}
    for r in order:
        slots[r.doc_id] = nth[want[r.doc_id]]
        nth[want[r.doc_id]] += 1
    assert {r.doc_id: r.slot for r in got} == slots
    small = sharding.histogram_shards(keyed, sharding.text_order(), F.col("size"), 16, most_rows=4, ties=("doc_id",)).collect()
    assert all(sorted(x.slot for x in small if x.shard == s) == list(range(sum(x.shard == s for x in small))) for s in range(16))


def test_tool_calls_link_order_and_validate(spark, data):
    call = {"tool_calls": [{"id": "b", "name": "add", "arguments": '{"y": 2, "x": "1"}', "depends_on": ["a"]}, {"id": "a", "name": "add", "arguments": '{"x":1}'}, {"id": "l1", "name": "nope", "arguments": "{", "depends_on": ["l2"]}, {"id": "l2", "name": "add", "arguments": "{}", "depends_on": ["l1"]}]}
    rows = [
        (1, 0, "assistant", json.dumps(call)), (1, 1, "tool", json.dumps({"tool_call_id": "a", "content": "3"})), (1, 2, "tool", json.dumps({"tool_call_id": "zz", "content": "?"})),
        (2, 0, "user", 'say "hi"'), (2, 1, "assistant", None), (2, 2, "system", "{broken"), (None, 0, "user", "x"), (3, None, None, ""),
    ]
    conv = spark.createDataFrame([(*r, "k", 1) for r in rows], "conv_id long, turn long, role string, text string, kind string, level int")
    tools = {"add": {"type": "object", "properties": {"x": {"type": "integer"}, "y": {"type": "integer"}}, "required": ["x", "y"]}, **chat.TOOLS}
    got = chat.tool_chat(conv, tools).collect()
    by = {(r.conv_id, r.call_id, r.kind): r for r in got}
    assert len(got) == 11 and by[1, "a", "call"].linked and by[1, "a", "result"].linked and not by[1, "zz", "result"].linked
    assert by[1, "b", "call"].position > by[1, "a", "result"].position and not by[1, "b", "call"].cycle and by[1, "l1", "call"].cycle
    assert by[1, "b", "call"].errors == "type x" and by[1, "a", "call"].errors == "missing y" and by[1, "l1", "call"].errors == "arguments are no JSON"
    assert json.loads(by[1, "b", "call"].json)["arguments"] == {"x": "1", "y": 2} and '"arguments":{"x":"1","y":2}' in by[1, "b", "call"].json
    assert by[2, "turn-0", "call"].linked and by[2, "turn-0", "result"].linked and json.loads(by[2, "turn-0", "call"].json)["arguments"]["prompt"] == 'say "hi"'
    for c in (1, 2):
        assert sorted(r.position for r in got if r.conv_id == c) == list(range(sum(r.conv_id == c for r in got)))
    real = table(spark, data, "conversations")
    out = chat.tool_chat(real)
    assert out.count() == real.count() and not re.search("Python|Pandas|Arrow", out._jdf.queryExecution().executedPlan().toString())
    assert chat.tool_chat(conv.limit(0)).count() == 0


def test_languages_are_learned_and_held_out(spark, docs, odd):
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4
    model = langid.fit(docs, fold != 2)
    got = {r.doc_id: r for r in langid.identify(docs, model).collect()}
    held = docs.filter(fold == 2).collect()
    right = langid.held_out([r.lang for r in held], [got[r.doc_id].lang_pred for r in held])
    assert min(right.values()) >= 0.9
    und = {r.doc_id: (r.lang_pred, r.score) for r in langid.identify(odd, model).collect()}
    assert all(und[i] == ("und", 0.0) for i in (0, 1, 2, 9)) and und[7][0] != "und"
    assert langid.fit(odd.limit(0), F.lit(True)) is None and {r.lang_pred for r in langid.identify(odd, None).collect()} == {"und"}
    one = langid.fit(odd.filter("doc_id = 7"), F.lit(True))
    assert {r.lang_pred for r in langid.identify(odd.filter("doc_id in (7, 8)"), one).collect()} == {"en"}
    assert langid.in_known_language(odd, model).columns == odd.columns
    text = " ".join(r.text for r in held[:50]).encode()
    for most in (100, 1000, 1 << 20):
        assert (langid.text_features(text, most) == langid.features([text])[0]).all()
    assert abs(langid.scaled(langid.counted([b"ab" * (1 << 17)]))).max() <= 1 and langid.counted([b"ab" * (1 << 17)]).max() > 1 << 16
