"""Order of linked calls against a plain topological sort, links of repeated identifiers, schemas."""

import json
import random

from pyspark.sql import functions as F

from cellbalance.llm import chat
from cellbalance.llm.common import Work, table

SCHEMA = "row long, conv_id long, turn long, m long, place int, kind string, call_id string, deps array<string>"


def plain_order(rows):
    """Rows of one conversation: each stands at the latest own place among all it waits for."""
    first = lambda kind, i: min((r for r in rows if r["kind"] == kind and r["call_id"] == i), key=lambda r: (r["at"], r["row"]), default=None)

    def needs(r):
        if r["kind"] == "result":
            call = first("call", r["call_id"])
            return [call] if call and first("result", r["call_id"]) is r else []
        return [first("result", d) or first("call", d) for d in set(r["deps"]) if first("call", d)] if r["kind"] == "call" else []

    def key(r, path=()):
        if r["row"] in path:
            return None
        held = [key(x, (*path, r["row"])) for x in needs(r)]
        if None in held:
            return None
        return (max([r["at"], *(k for k, _ in held)]), max([0, *(n + 1 for _, n in held)]))

    def final(r):
        k = key(r)
        if r["kind"] == "result" and needs(r):
            call = needs(r)[0]
            ck = key(call) or (call["at"], 0)
            return (max(r["at"], ck[0]), ck[1] + 1)
        return k or (r["at"], 0)

    return sorted(rows, key=lambda r: (*final(r), r["at"], r["row"])), {r["row"]: key(r) is None and r["kind"] == "call" for r in rows}


def test_order_is_that_of_a_plain_sort(spark):
    rng, rows = random.Random(8), []
    for conv in range(60):
        n = rng.randrange(1, 7)
        turns = rng.sample(range(40), 2 * n)
        for i in range(n):
            deps = [f"c{rng.randrange(n + 1)}" for _ in range(rng.choice((0, 0, 1, 1, 2)))]
            rows.append((len(rows), conv, turns[i], rng.randrange(-9, 9) << 55, 0, "call", f"c{rng.randrange(n) if conv % 7 == 0 else i}", deps))
        for i in range(n):
            if rng.random() < 0.7:
                rows.append((len(rows), conv, turns[n + i], rng.randrange(-9, 9) << 55, 1, "result", f"c{i}", []))
        rows.append((len(rows), conv, 1, 5, 2, "message", None, []))
    found = spark.createDataFrame(rows, SCHEMA)
    got = {r.row: r for r in chat.positioned(chat.ordered(Work(spark), found)).collect()}
    cycles = moved = 0
    for conv in range(60):
        mine = [dict(zip(("row", "conv_id", "turn", "m", "place", "kind", "call_id", "deps"), r, strict=True)) | {"at": (r[2], r[3], r[4])} for r in rows if r[1] == conv]
        want, stuck = plain_order(mine)
        assert [r["row"] for r in sorted(mine, key=lambda r: got[r["row"]].position)] == [r["row"] for r in want]
        assert {r["row"]: got[r["row"]].cycle for r in mine} == stuck
        place = {r["row"]: got[r["row"]].position for r in mine}
        moved += want != sorted(mine, key=lambda r: (r["at"], r["row"]))
        cycles += any(stuck.values())
        for r in mine:  # nothing stands before what it waits for, cycles aside
            for d in r["deps"] if r["kind"] == "call" and not stuck[r["row"]] else ():
                assert all(place[x["row"]] < place[r["row"]] for x in mine if x["call_id"] == d and got[x["row"]].link_turn is not None)
    assert cycles > 3 and moved > 3


def test_plain_threads_keep_their_turns(spark, data):
    real = table(spark, data, "conversations")
    got = chat.tool_chat(real)
    assert got.filter("position is null or cycle or errors <> ''").count() == 0
    assert got.groupBy("conv_id").agg(F.expr("max(position) - count(*) + 1").alias("x")).filter("x <> 0").count() == 0
    both = got.alias("a").join(got.alias("b"), F.expr("a.conv_id = b.conv_id and a.position < b.position and a.turn > b.turn"))
    assert both.count() == 0
    assert got.filter("kind = 'result' and linked and link_turn <> turn - 1").count() == 0


def test_repeated_identifiers_link_once(spark):
    call = lambda i: json.dumps({"tool_calls": [{"id": i, "name": "respond", "arguments": '{"prompt":"p"}'}]})
    answer = lambda i: json.dumps({"tool_call_id": i, "content": "r"})
    rows = [(1, 0, "assistant", call("a")), (1, 1, "assistant", call("a")), (1, 2, "tool", answer("a")), (1, 3, "tool", answer("a")), (2, 5, "user", "x"), (2, 5, "user", "x"), (2, 6, "assistant", "y"), (None, 0, "user", "x"), (3, None, "user", "x")]
    got = chat.tool_chat(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()
    assert sorted((r.turn, r.kind, r.linked, r.link_turn) for r in got if r.conv_id == 1) == [(0, "call", True, 2), (1, "call", False, None), (2, "result", True, 0), (3, "result", False, None)]
    assert sorted((r.kind, r.linked) for r in got if r.conv_id == 2) == [("call", False), ("call", True), ("result", True)]
    assert [(r.position, r.linked) for r in got if r.conv_id in (None, 3)] == [(None, False)] * 2
    assert all('"linked":true' in r.json or not r.linked for r in got)


def test_arguments_are_checked_as_a_schema_does(spark):
    tool = {
        "type": "object", "required": ["n"], "additionalProperties": False,
        "properties": {
            "n": {"type": "number"}, "i": {"type": "integer"}, "s": {"type": ["string", "null"]}, "e": {"enum": ["a", 2, None]}, "l": {"type": "array", "items": {"type": "integer"}},
            "o": {"type": "object", "properties": {"x": {"type": "boolean"}, "y": {"type": "array", "items": {"type": "object", "required": ["z"]}}}, "required": ["x"]}, "any": {},
        },
    }
    cases = {
        '{"n":3}': "", '{"n":1.0,"i":2.0}': "", '{"n":1e3,"i":3}': "", '{"n":"3"}': "type n", '{"n":1,"i":2.5}': "type i", '{"n":1,"s":null}': "", '{"n":1,"s":"x"}': "", '{"n":1,"s":4}': "type s",
        '{"n":1,"e":"a"}': "", '{"n":1,"e":2}': "", '{"n":1,"e":null}': "", '{"n":1,"e":"b"}': "value e", '{"n":1,"l":[1,2]}': "", '{"n":1,"l":[1,"2","3"]}': "type l[]", '{"n":1,"l":{}}': "type l",
        '{"n":1,"o":{"x":true,"w":1}}': "", '{"n":1,"o":{}}': "missing o.x", '{"n":1,"o":{"x":1,"y":[{"z":1},{}]}}': "missing o.y[].z;type o.x", '{"i":1,"q":2}': "missing n;unknown q", "[1]": "type arguments",
        '{"n":1,"any":[{}]}': "", "{": "arguments are no JSON", None: "arguments are no JSON",
    }
    text = lambda a: json.dumps({"tool_calls": [{"id": "k", "name": "t", "arguments": a}]})
    conv = spark.createDataFrame([(i, 0, "assistant", text(a)) for i, a in enumerate(cases)], "conv_id long, turn long, role string, text string")
    got = {r.conv_id: r.errors for r in chat.tool_chat(conv, {"t": tool}).collect()}
    assert [got[i] for i in range(len(cases))] == list(cases.values())


def test_text_and_result_beside_calls_stay(spark):
    call = lambda i: [{"id": i, "name": "respond", "arguments": '{"prompt":"p"}'}]
    texts = [
        {"tool_calls": call("a"), "content": "Let me look."},
        {"tool_calls": call("b"), "tool_call_id": "a", "content": "42"},
        {"tool_calls": call("c"), "tool_call_id": "b"},
        {"tool_calls": call("d"), "content": ""},
        {"tool_calls": call("e"), "content": None},
    ]
    conv = spark.createDataFrame([(1, i, "assistant", json.dumps(t)) for i, t in enumerate(texts)], "conv_id long, turn long, role string, text string")
    got = chat.tool_chat(conv).collect()
    assert sorted((r.turn, r.kind, r.call_id, r.linked) for r in got if r.kind != "message") == [
        (0, "call", "a", True), (1, "call", "b", True), (1, "result", "a", True), (2, "call", "c", False), (2, "result", "b", True), (3, "call", "d", False), (4, "call", "e", False)
    ]
    assert [(r.turn, json.loads(r.json)["content"]) for r in got if r.kind == "message"] == [(0, "Let me look.")]
    by = {(r.call_id, r.kind): r for r in got}
    assert json.loads(by["a", "result"].json)["content"] == "42" and by["a", "result"].position > by["a", "call"].position
    assert by[None, "message"].position < by["a", "call"].position and sorted(r.position for r in got) == list(range(8))


def test_a_very_long_text_and_a_long_chain(spark):
    n = 12  # each call stands before the one it needs
    calls = [{"tool_calls": [{"id": f"c{i}", "name": "respond", "arguments": '{"prompt":"p"}', "depends_on": [f"c{i + 1}"] if i < n - 1 else []}]} for i in range(n)]
    rows = [(1, i, "assistant", json.dumps(c)) for i, c in enumerate(calls)] + [(2, 0, "user", "word " * 300_000)]
    got = chat.tool_chat(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()
    assert [r.turn for r in sorted((r for r in got if r.conv_id == 1), key=lambda r: r.position)] == list(range(n - 1, -1, -1))
    assert len(json.loads(next(r.json for r in got if r.conv_id == 2))["arguments"]["prompt"]) == 1_500_000
