"""Chat formatting with tool-call linking, in DataFrame functions only.

Messages become events. An assistant text that is a JSON object with `tool_calls` (id, name, arguments,
depends_on) yields one call event per entry, a text with `tool_call_id` yields a result event. A text with both
yields both; content that is not empty and belongs to no result yields a message event before the calls. Plain
conversations follow the implicit contract that an answer is the result of the turn before it: a user
turn is a call of `respond` with the identifier turn-N, and an assistant turn right after it is that
call's result. Calls and results meet in one hash join by (conversation, identifier): the first call of an
identifier and its first result are linked, and each names the other's turn and place.

Order: a result stands after its call, a call after the results of the calls it depends on (after the calls
themselves where they have none), and nothing else moves. An event whose needs all stand before it keeps its
place; any other stands right after the last event it waits for. So events sort by the latest (turn, message,
place) among themselves and all they wait for, then by the length of the chain of needs, then by their own.
Only conversations with a call that stands before one of its needs go through rounds, one for each step of the
longest chain there; a round looks at calls that the round before could have freed and writes those that are
free now. What is never placed stands on a cycle or behind one, keeps its own place and is marked `cycle`.
Positions come from counts by (turn, part of the message hash) and by 1024 turns plus a rank within such a
part, so a conversation with very many turns, or very many messages of one turn, is not ranked by one task.

Arguments are checked against the schemas of the tools (type, properties, required, additionalProperties,
items, enum, to any depth): missing and unknown names, wrong types and values off the list are named. Each
event becomes one canonical JSON line: keys sorted, no spaces, numbers in one form.

Defined results: null or empty texts are plain messages with empty content; text that looks like JSON
but is not is plain; a result without its call, or a call without a result, stays and is not linked; later
calls and results of a linked identifier stay and are not linked; a need that names no call is ignored; null
conversation ids or turns never link and have a null position. Messages of one turn go by a hash of role and
text. Extra columns are not read.
"""

from __future__ import annotations

import json
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellbalance.llm.common import Work

#: Schemas of arguments by tool.
TOOLS = {"respond": {"type": "object", "properties": {"prompt": {"type": "string"}, "turn": {"type": "integer"}}, "required": ["prompt"], "additionalProperties": False}}
_CALLS = "array<struct<id:string,name:string,arguments:string,depends_on:array<string>>>"
_NONE = "array<string>"


def events(conversations: DataFrame) -> DataFrame:
    """conv_id, turn, m (hash of role and text), place, role, kind (call, result, message), call_id, name,
    arguments (JSON), deps, content."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    base = conversations.select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), text.alias("content")
    ).withColumn("m", F.xxhash64("role", "content"))
    shaped = base.withColumn("body", F.when(F.col("content").startswith("{"), F.col("content")))
    shaped = (
        shaped.withColumn("calls", F.from_json(F.get_json_object("body", "$.tool_calls"), _CALLS))
        .withColumn("answers", F.get_json_object("body", "$.tool_call_id"))
        .withColumn("said", F.get_json_object("body", "$.content"))
        .drop("body")
    )
    none, listed = F.lit(None).cast("string"), F.coalesce(F.size("calls"), F.lit(0)) > 0
    dep = F.lit(None).cast("array<string>")
    implicit = F.concat(F.lit("turn-"), F.col("turn").cast("string"))
    implied = F.to_json(F.struct(F.col("content").alias("prompt"), F.col("turn").alias("turn")))
    own = F.array(
        F.when(F.col("answers").isNotNull(), F.struct(F.lit("result").alias("kind"), F.col("answers").alias("id"), none.alias("name"), none.alias("arguments"), dep.alias("deps")))
        .when(F.col("role") == "user", F.struct(F.lit("call").alias("kind"), implicit.alias("id"), F.lit("respond").alias("name"), implied.alias("arguments"), dep.alias("deps")))
        .when(
            F.col("role") == "assistant",
            F.struct(F.lit("result").alias("kind"), F.concat(F.lit("turn-"), (F.col("turn") - 1).cast("string")).alias("id"), none.alias("name"), none.alias("arguments"), dep.alias("deps")),
        )
        .otherwise(F.struct(F.lit("message").alias("kind"), none.alias("id"), none.alias("name"), none.alias("arguments"), dep.alias("deps")))
    )
    calls = F.transform("calls", lambda c: F.struct(F.lit("call").alias("kind"), c["id"].alias("id"), c["name"].alias("name"), c["arguments"].alias("arguments"), c["depends_on"].alias("deps")))
    beside = F.array(
        F.when(F.col("answers").isNotNull(), F.struct(F.lit("result").alias("kind"), F.col("answers").alias("id"), none.alias("name"), none.alias("arguments"), dep.alias("deps")))
        .when(F.col("said") != "", F.struct(F.lit("message").alias("kind"), none.alias("id"), none.alias("name"), none.alias("arguments"), dep.alias("deps")))
    )
    both = F.concat(F.filter(beside, lambda x: x.isNotNull()), calls)
    return shaped.select(
        "conv_id", "turn", "m", "role", F.when(listed | F.col("answers").isNotNull(), F.coalesce("said", F.lit(""))).otherwise(F.col("content")).alias("content"),
        F.posexplode(F.when(listed, both).otherwise(own)).alias("place", "e"),
    ).select("conv_id", "turn", "m", "place", "role", "e.kind", F.col("e.id").alias("call_id"), "e.name", "e.arguments", F.coalesce("e.deps", F.array().cast("array<string>")).alias("deps"), "content")


AT = ("turn", "m", "place")


def _at(prefix: str = "") -> Column:
    return F.struct(*[F.col(f"{prefix}{c}").alias(c) for c in AT])


def links(found: DataFrame) -> DataFrame:
    """(conv_id, call_id, call, result) of the first call and the first result of each identifier: structs of
    turn, m, place and row; result is null for a call without one."""
    ids = found.filter("conv_id is not null and call_id is not null and turn is not null")
    first = lambda kind: ids.filter(f"kind = '{kind}'").groupBy("conv_id", "call_id").agg(F.min(F.struct(*AT, "row")).alias(kind))
    return first("call").join(first("result"), ["conv_id", "call_id"], "left")


def _later(a: Column, b: Column) -> Column:
    return F.when(b.isNull() | (a >= b), a).otherwise(b)


def _bare(held: str) -> Column:
    return F.when(F.col(held).isNotNull(), F.struct(*[F.col(f"{held}.{c}").alias(c) for c in AT]))


def placed_calls(work: Work, found: DataFrame, pairs: DataFrame) -> DataFrame:
    """(row, k, level) of the calls of conversations in which a call stands before one of its needs: k is the
    latest (turn, m, place) of the call and all it waits for, level the length of its chain of needs. Calls on
    a cycle or behind one have a null k."""
    nodes = pairs.select("conv_id", F.col("call_id").alias("needs"), F.col("call.row").alias("row"), _bare("call").alias("own"), _bare("result").alias("answer"))
    nodes = nodes.withColumn("end", _later(F.col("own"), F.col("answer")))
    calls = found.filter("kind = 'call' and conv_id is not null and turn is not null and size(deps) > 0")
    arcs = calls.select("conv_id", "row", _at().alias("own"), F.explode(F.array_distinct("deps")).alias("needs")).join(nodes.select("conv_id", "needs", "end"), ["conv_id", "needs"])
    arcs = work.table(arcs, "arcs")
    twisted = arcs.filter("own <= end").select("conv_id").distinct()
    waits = work.table(arcs.join(twisted, "conv_id").select("conv_id", "row", "own", "needs"), "waits")
    if waits.isEmpty():
        return waits.select("row", F.col("own").alias("k"), F.lit(0).cast("long").alias("level"))
    nodes = work.table(nodes.join(waits.select("conv_id").distinct(), "conv_id"), "nodes")
    folder = f"{work.root}/placed"

    def place(calls: DataFrame, nth: int) -> DataFrame:
        """Write the calls (row, k, level) that are free in this round; those that others name, with the k and
        level of their results."""
        ended = calls.join(nodes.drop("own", "end"), "row", "left").select("row", "k", "level", "conv_id", "needs", _later(F.col("k"), F.col("answer")).alias("end"), (F.col("level") + F.col("answer").isNotNull().cast("long")).alias("end_level"))
        ended.write.mode("overwrite").parquet(f"{folder}/round={nth}")
        return work.spark.read.schema(ended.schema).parquet(f"{folder}/round={nth}")

    free = nodes.join(waits.select("row").distinct(), "row", "left_anti").select("row", F.col("own").alias("k"), F.lit(0).cast("long").alias("level"))
    fresh, nth = place(free, 0), 0
    while not fresh.isEmpty():
        nth += 1
        every = work.spark.read.schema(fresh.schema).parquet(folder).filter("needs is not null").select("conv_id", "needs", "end", "end_level")
        touched = waits.join(fresh.filter("needs is not null").select("conv_id", "needs"), ["conv_id", "needs"]).select("row").distinct()
        held = waits.join(touched, "row").join(every, ["conv_id", "needs"], "left").groupBy("row", "own")
        ready = held.agg(F.count("*").alias("all"), F.count("end_level").alias("met"), F.max("end").alias("last"), (F.max("end_level") + 1).alias("level")).filter("all = met")
        fresh = place(ready.select("row", _later(F.col("own"), F.col("last")).alias("k"), "level"), nth)
    done = work.spark.read.schema(fresh.schema).parquet(folder).select("row", "k", "level")
    stuck = waits.select("row").distinct().join(done, "row", "left_anti")
    return done.unionByName(stuck, allowMissingColumns=True)


def ordered(work: Work, found: DataFrame) -> DataFrame:
    """row, conv_id, turn, m, place, k, level, cycle, link_turn and link_place of every event."""
    pairs = work.table(links(found), "links")
    calls = work.table(placed_calls(work, found, pairs), "calls")
    both = pairs.filter("result is not null")
    ends = both.select(F.col("call.row").alias("row"), F.col("result.turn").alias("link_turn"), F.col("result.place").alias("link_place"), F.lit(None).cast("long").alias("of"), F.lit(None).cast("struct<turn:long,m:long,place:int>").alias("call"))
    ends = ends.union(both.select("result.row", "call.turn", "call.place", "call.row", _bare("call")))
    slim = found.select("row", "conv_id", *AT, _at().alias("own")).join(ends, "row", "left")
    slim = slim.join(calls.select("row", F.col("k").alias("own_k"), F.col("level").alias("own_level"), F.lit(True).alias("moved")), "row", "left")
    slim = slim.join(calls.select(F.col("row").alias("of"), F.col("k").alias("call_k"), F.col("level").alias("call_level")), "of", "left")
    k = _later(F.coalesce("own_k", "own"), F.coalesce("call_k", "call"))
    level = F.coalesce("own_level", F.when(F.col("of").isNotNull(), F.coalesce("call_level", F.lit(0)) + 1), F.lit(0)).cast("long")
    return slim.select("row", "conv_id", *AT, k.alias("k"), level.alias("level"), (F.col("moved").isNotNull() & F.col("own_k").isNull()).alias("cycle"), "link_turn", "link_place")


def positioned(df: DataFrame, block: int = 1024) -> DataFrame:
    """Events with `position`, their place in the conversation's order, from 0."""
    df = df.withColumn("kt", F.col("k.turn")).withColumn("km", F.shiftright("k.m", 56))
    named = df.filter("conv_id is not null and turn is not null")
    fine = named.groupBy("conv_id", "kt", "km").agg(F.count("*").alias("n")).withColumn("block", F.floor(F.col("kt") / block))
    before = lambda w: F.coalesce(F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    coarse = fine.groupBy("conv_id", "block").agg(F.sum("n").alias("n")).withColumn("far", before(Window.partitionBy("conv_id").orderBy("block"))).drop("n")
    skips = fine.withColumn("near", before(Window.partitionBy("conv_id", "block").orderBy("kt", "km"))).join(coarse, ["conv_id", "block"])
    skips = skips.select("conv_id", "kt", "km", (F.col("near") + F.col("far")).alias("skip"))
    inside = Window.partitionBy("conv_id", "kt", "km").orderBy("k.m", "k.place", "level", "turn", "m", "place", "row")
    ranked = named.withColumn("nth", F.row_number().over(inside) - 1).join(skips, ["conv_id", "kt", "km"])
    out = ranked.withColumn("position", F.col("skip") + F.col("nth")).drop("skip", "nth")
    rest = df.filter("conv_id is null or turn is null").withColumn("position", F.lit(None).cast("long"))
    return out.unionByName(rest).drop("kt", "km")


_KINDS = {
    "string": lambda kind, v: kind == "STRING",
    "boolean": lambda kind, v: kind == "BOOLEAN",
    "null": lambda kind, v: kind == "VOID",
    "object": lambda kind, v: kind.startswith("OBJECT"),
    "array": lambda kind, v: kind.startswith("ARRAY"),
    "number": lambda kind, v: kind.rlike("^(BIGINT|DOUBLE|FLOAT|DECIMAL)"),
    "integer": lambda kind, v: (kind == "BIGINT") | (kind.rlike("^(DOUBLE|FLOAT|DECIMAL)") & (F.coalesce(F.try_variant_get(v, "$", "double") % 1, F.lit(1.0)) == 0)),
}


def schema_errors(v: Column, schema: dict, path: str = "") -> Column:
    """What is wrong with a variant by a schema, as an array of names."""
    empty, name = F.array().cast(_NONE), path or "arguments"
    kind = F.coalesce(F.schema_of_variant(v), F.lit("VOID"))
    found = []
    if "enum" in schema:
        listed = [json.dumps(x, separators=(",", ":"), sort_keys=True, ensure_ascii=False) for x in schema["enum"]]
        found.append(F.when(F.coalesce(F.to_json(v), F.lit("null")).isin(listed), empty).otherwise(F.array(F.lit(f"value {name}"))))
    if "properties" in schema or "required" in schema or schema.get("additionalProperties") is False:
        names = F.coalesce(F.json_object_keys(F.to_json(v)), empty)
        inner, dot = [], f"{path}." if path else ""
        known = F.array(*[F.lit(p) for p in schema.get("properties", {})]).cast(_NONE)
        inner.append(F.transform(F.array_except(F.array(*[F.lit(p) for p in schema.get("required", [])]).cast(_NONE), names), lambda p: F.concat(F.lit(f"missing {dot}"), p)))
        if schema.get("additionalProperties") is False:
            inner.append(F.transform(F.array_except(names, known), lambda p: F.concat(F.lit(f"unknown {dot}"), p)))
        for p, sub in schema.get("properties", {}).items():
            child = F.try_variant_get(v, f"$['{p}']", "variant")
            inner.append(F.when(F.array_contains(names, p), schema_errors(child, sub, dot + p)).otherwise(empty))
        found.append(F.when(kind.startswith("OBJECT"), F.concat(*inner)).otherwise(empty))
    if "items" in schema:
        each = F.transform(F.try_variant_get(v, "$", "array<variant>"), lambda x: schema_errors(x, schema["items"], f"{path}[]"))
        found.append(F.when(kind.startswith("ARRAY"), F.array_distinct(F.flatten(each))).otherwise(empty))
    rest = F.concat(*found) if found else empty
    if "type" not in schema:
        return rest
    kinds = [schema["type"]] if isinstance(schema["type"], str) else schema["type"]
    fits = reduce(lambda x, y: x | y, [_KINDS[k](kind, v) for k in kinds])
    return F.when(fits, rest).otherwise(F.array(F.lit(f"type {name}")))


def validated(df: DataFrame, tools: dict = TOOLS) -> DataFrame:
    """Events with `arguments` in canonical form and `errors`, sorted names of what is wrong."""
    df = df.withColumn("parsed", F.when(F.col("kind") == "call", F.try_parse_json("arguments")))
    errors = F.when(F.col("kind") != "call", F.array().cast(_NONE)).when(F.col("parsed").isNull(), F.array(F.lit("arguments are no JSON")))
    for tool, schema in sorted(tools.items()):
        errors = errors.when(F.col("name") == tool, F.array_sort(schema_errors(F.col("parsed"), schema)))
    return df.withColumn("errors", errors.otherwise(F.array(F.lit("unknown tool")))).withColumn("arguments", F.to_json("parsed")).drop("parsed")


def formatted(df: DataFrame) -> DataFrame:
    """One canonical JSON line an event; null fields are left out and keys are in order."""
    line = F.struct(
        F.parse_json(F.coalesce("arguments", F.lit("null"))).alias("arguments"),
        F.col("call_id").alias("call_id"),
        F.when(F.col("kind") == "call", F.lit(None).cast("string")).otherwise(F.col("content")).alias("content"),
        F.when(F.size("errors") > 0, F.col("errors")).alias("errors"),
        F.col("kind").alias("kind"),
        F.col("linked").alias("linked"),
        F.col("name").alias("name"),
        F.col("role").alias("role"),
    )
    bare = F.struct(*[F.col(c) if c != "content" else F.col("content") for c in ("call_id", "content", "kind", "linked", "role")])
    return df.withColumn("json", F.when(F.col("kind") == "call", F.to_json(line)).otherwise(F.to_json(bare)))


def tool_chat(conversations: DataFrame, tools: dict = TOOLS) -> DataFrame:
    """conv_id, position, turn, kind, call_id, linked, link_turn, link_place, cycle, errors, json of every event."""
    work = Work(conversations.sparkSession)
    found = work.table(events(conversations).withColumn("row", F.monotonically_increasing_id()), "events")
    order = positioned(ordered(work, found.select("row", "conv_id", *AT, "kind", "call_id", "deps")))
    placed = found.join(order.select("row", "position", "cycle", "link_turn", "link_place"), "row").withColumn("linked", F.col("link_turn").isNotNull())
    lines = formatted(validated(placed, tools))
    return lines.select("conv_id", "position", "turn", "kind", "call_id", "linked", "link_turn", "link_place", "cycle", F.array_join("errors", ";").alias("errors"), "json")
