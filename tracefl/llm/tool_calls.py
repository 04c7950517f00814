"""Chat formatting: tool calls linked with their results, ordered, validated and written as canonical JSON.

Calls (conv_id, turn, call_id, name, arguments as JSON, depends_on) and results (conv_id, turn, call_id, content) are
joined by hash on (conv_id, call_id). An order is topological if each call comes after what it depends on. As
dependencies nearly always point to earlier turns, a call's place is its own turn raised to the places of its
dependencies: rounds of a join and a grouped maximum, which end when nothing rises (at once, if every
dependency is earlier). So a conversation of any length is never gathered in one task; only calls that
end up with the place of one of their own dependencies are ordered among themselves, by conversation and place, and those on a
cycle are marked.

Arguments are checked against the tool's JSON schema (type, enum, const, required, properties, additionalProperties,
items, minLength, maxLength, minimum, maximum, minItems, maxItems); schemas are a small table given by the user.
Canonical JSON: keys in code point order, no spaces, no escapes but those that JSON needs.

Defined results: a call without a result has status `pending`, a result without a call `orphan`, one identifier used
twice in a conversation links each of its calls with the first of its results by turn; null identifiers never link; unknown tools,
arguments that aren't JSON objects, nest deeper than the reader goes or hold NaN or infinite numbers, null arguments, and types that the schema
language lacks are errors, not failures; lone surrogates are escaped; equal calls are rows of their own; further columns don't count; empty tables give empty tables.
"""

from __future__ import annotations

import json
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut_lineage, split_join

_TYPES = {"object": dict, "array": list, "string": str, "boolean": bool, "null": type(None)}


def escaped(text: str) -> str:
    """Surrogates without a partner, which UTF-8 can't say, as JSON escapes."""
    return re.sub("[\ud800-\udfff]", lambda m: f"\\u{ord(m[0]):04x}", text)


def canonical(value: object) -> str:
    return escaped(json.dumps(value, ensure_ascii=False, sort_keys=True, separators=(",", ":")))


def _finite(text: str) -> float:
    value = float(text)
    if not math.isfinite(value):
        raise ValueError(text)
    return value


def parsed(arguments: str) -> tuple[object, str, list[str]]:
    """(value, its canonical JSON, errors); what isn't JSON, nests too deep to read or holds a number that JSON can't say stays a string."""
    try:
        value = json.loads(arguments, parse_float=_finite, parse_constant=_finite)
        return value, canonical(value), [] if isinstance(value, dict) else ["$: not an object"]
    except (ValueError, RecursionError):
        return arguments, canonical(arguments), ["$: not JSON"]


def _is(value: object, kind: str) -> bool:
    if kind in ("number", "integer"):
        return isinstance(value, (int, float)) and not isinstance(value, bool) and (kind == "number" or isinstance(value, int) or value.is_integer())
    return kind in _TYPES and isinstance(value, _TYPES[kind])


def errors(value: object, schema: dict, at: str = "$") -> list[str]:
    """What in the value the schema forbids, as 'path: reason'."""
    kinds = schema.get("type")
    kinds = [kinds] if isinstance(kinds, str) else kinds
    if kinds and not any(_is(value, k) for k in kinds):
        return [f"{at}: not of type {'/'.join(kinds)}"]
    out = []
    if "enum" in schema and value not in schema["enum"]:
        out.append(f"{at}: not in enum")
    if "const" in schema and value != schema["const"]:
        out.append(f"{at}: not the constant")
    bounds = {str: ("minLength", "maxLength", len), list: ("minItems", "maxItems", len), int: ("minimum", "maximum", lambda v: v), float: ("minimum", "maximum", lambda v: v)}
    for kind, (least, most, size) in bounds.items():
        if isinstance(value, kind) and not isinstance(value, bool):
            if least in schema and size(value) < schema[least]:
                out.append(f"{at}: below {least}")
            if most in schema and size(value) > schema[most]:
                out.append(f"{at}: above {most}")
    if isinstance(value, dict):
        known = schema.get("properties", {})
        out += [f"{at}.{k}: missing" for k in schema.get("required", []) if k not in value]
        more = schema.get("additionalProperties", True)
        for k in sorted(value):
            if k in known:
                out += errors(value[k], known[k], f"{at}.{k}")
            elif more is False:
                out.append(f"{at}.{k}: not allowed")
            elif isinstance(more, dict):
                out += errors(value[k], more, f"{at}.{k}")
    if isinstance(value, list) and isinstance(schema.get("items"), dict):
        for i, x in enumerate(value):
            out += errors(x, schema["items"], f"{at}[{i}]")
    return out


def places(calls: DataFrame) -> DataFrame:
    """(conv_id, call_id, place, step, cyclic): calls in the order (place, step, turn, call_id) come after what they depend on."""
    own = cut_lineage(calls.where("call_id is not null").groupBy("conv_id", "call_id").agg(F.min("turn").alias("turn"), F.flatten(F.collect_list(F.coalesce("depends_on", F.array().cast("array<string>")))).alias("deps")))
    edges = own.select("conv_id", "call_id", "turn", F.explode(F.array_distinct("deps")).alias("dep"))
    known = own.select(F.col("conv_id").alias("_c"), F.col("call_id").alias("dep"), F.col("turn").alias("dep_turn"))
    edges = cut_lineage(edges.join(known, (F.col("conv_id") == F.col("_c")) & (edges["dep"] == known["dep"])).select("conv_id", "call_id", edges["dep"], "turn", "dep_turn"))
    place = own.select("conv_id", "call_id", F.col("turn").alias("place"), F.lit(None).cast("string").alias("jump"))
    if edges.where("dep_turn >= turn").isEmpty():
        return own.select("conv_id", "call_id", F.col("turn").alias("place"), F.lit(0).alias("step"), F.lit(False).alias("cyclic"))
    # a call's jump is the furthest call that its place came from, one more link to follow: a chain of n calls settles in some log n rounds.
    # Places only rise, and only to turns that there are: so this ends, with cycles too
    while True:
        at = place.select(F.col("conv_id").alias("_c"), F.col("call_id").alias("_d"), F.col("place").alias("p"), F.col("jump").alias("_jump"))
        links = edges.select("conv_id", "call_id", "dep").unionAll(place.where("jump is not null").select("conv_id", "call_id", F.col("jump").alias("dep")))
        raised = links.join(at, (F.col("conv_id") == F.col("_c")) & (F.col("dep") == F.col("_d"))).groupBy("conv_id", "call_id").agg(F.max(F.struct("p", F.coalesce("_jump", "dep").alias("to"))).alias("r"))
        new = cut_lineage(split_join(place, raised, ["conv_id", "call_id"], "left").withColumn("up", F.coalesce(F.col("r.p") > F.col("place"), F.lit(False))))
        place = new.select("conv_id", "call_id", F.when(F.col("up"), F.col("r.p")).otherwise(F.col("place")).alias("place"), F.when(F.col("up"), F.col("r.to")).otherwise(F.col("jump")).alias("jump"))
        if new.where("up").isEmpty():
            break
    # a call and its dependency in one place: what is left to order is small
    at = place.select(F.col("conv_id").alias("_c"), F.col("call_id").alias("_d"), F.col("place").alias("p"))
    mine = place.select(F.col("conv_id").alias("_c2"), F.col("call_id").alias("_i"), "place")
    tied = edges.join(at, (F.col("conv_id") == F.col("_c")) & (F.col("dep") == F.col("_d"))).join(mine, (F.col("conv_id") == F.col("_c2")) & (F.col("call_id") == F.col("_i"))).where("p = place").select("conv_id", "place", "call_id", "dep")

    def order(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        needs: dict[str, set[str]] = {}
        for c, d in zip(table["call_id"].to_pylist(), table["dep"].to_pylist(), strict=True):
            needs.setdefault(c, set()).add(d)
            needs.setdefault(d, set())
        step, left, n = {}, dict(needs), 0
        while ready := [c for c, d in left.items() if not (d & left.keys())]:
            for c in ready:
                step[c] = n
            left = {c: d for c, d in left.items() if c not in step}
            n += 1
        ids = sorted(needs)
        return pa.table({"conv_id": pa.array([key[0].as_py()] * len(ids), table["conv_id"].type), "call_id": ids, "step": pa.array([step.get(c, n) for c in ids], pa.int32()), "cyclic": [c not in step for c in ids]})

    kind = calls.schema["conv_id"].dataType.simpleString()
    steps = tied.groupBy("conv_id", "place").applyInArrow(order, f"conv_id {kind}, call_id string, step int, cyclic boolean")
    return split_join(place.drop("jump"), steps, ["conv_id", "call_id"], "left").select("conv_id", "call_id", "place", F.coalesce("step", F.lit(0)).alias("step"), F.coalesce("cyclic", F.lit(False)).alias("cyclic"))


def link(calls: DataFrame, results: DataFrame, schemas: dict[str, dict]) -> DataFrame:
    """One row for each call and each orphan result: conv_id, call_id, turn, status, place, step, cyclic, n_errors, first_error and json (canonical)."""
    calls = calls.select("conv_id", "turn", "call_id", "name", "arguments", "depends_on")
    results = results.select("conv_id", "turn", "call_id", "content")
    first = results.where("call_id is not null").groupBy("conv_id", "call_id").agg(F.min(F.struct("turn", "content")).alias("r")).select("conv_id", "call_id", F.col("r.turn").alias("r_turn"), F.col("r.content").alias("content"))
    linked = split_join(calls.withColumn("_call", F.lit(True)), first, ["conv_id", "call_id"], "left")
    linked = split_join(linked, places(calls), ["conv_id", "call_id"], "left")
    orphans = results.alias("r").join(calls.select("conv_id", "call_id").distinct().alias("c"), (F.col("r.conv_id") == F.col("c.conv_id")) & (F.col("r.call_id") == F.col("c.call_id")), "left_anti")
    orphans = orphans.select("conv_id", "call_id", "turn", F.lit(False).alias("_call"), "content", F.col("turn").alias("r_turn"))
    rows = linked.unionByName(orphans, allowMissingColumns=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            status, n, first_error, text = [], [], [], []
            for is_call, call_id, name, arguments, deps, content, r_turn in zip(*[batch.column(i).to_pylist() for i in range(6, 13)], strict=True):
                if not is_call:
                    status.append("orphan")
                    n.append(0)
                    first_error.append(None)
                    text.append(canonical({"id": call_id, "result": content}))
                    continue
                value, written_, found = parsed(arguments) if arguments is not None else (None, "null", ["$: not an object"])
                if name not in schemas:
                    found = [f"unknown tool {name}", *found]
                elif not found:
                    found = errors(value, schemas[name])
                done = r_turn is not None
                status.append("linked" if done else "pending")
                n.append(len(found))
                first_error.append(escaped(found[0]) if found else None)
                rest = {"depends_on": sorted({x for x in deps or [] if x is not None}), "id": call_id, "name": name} | ({"result": content} if done else {})
                text.append(f'{{"arguments":{written_},{canonical(rest)[1:]}')
            yield pa.RecordBatch.from_arrays([*batch.columns[:6], pa.array(status, pa.string()), pa.array(n, pa.int32()), pa.array(first_error, pa.string()), pa.array(text, pa.string())], ["conv_id", "call_id", "turn", "place", "step", "cyclic", "status", "n_errors", "first_error", "json"])

    kind, turn = calls.schema["conv_id"].dataType.simpleString(), calls.schema["turn"].dataType.simpleString()
    ordered = rows.select("conv_id", "call_id", "turn", F.coalesce("place", "turn").alias("place"), F.coalesce("step", F.lit(0)).alias("step"), F.coalesce("cyclic", F.lit(False)).alias("cyclic"), "_call", F.col("call_id").alias("_id"), "name", "arguments", "depends_on", "content", "r_turn")
    return ordered.mapInArrow(run, f"conv_id {kind}, call_id string, turn {turn}, place {turn}, step int, cyclic boolean, status string, n_errors int, first_error string, json string")


#: The tools that ``from_messages`` uses.
SCHEMAS = {
    "reply": {"type": "object", "required": ["prompt", "words"], "additionalProperties": False, "properties": {"prompt": {"type": "string", "minLength": 1}, "words": {"type": "integer", "minimum": 1, "maximum": 4096}}},
    "instruct": {"type": "object", "required": ["rule"], "additionalProperties": False, "properties": {"rule": {"type": "string", "minLength": 1}}},
}


def from_messages(messages: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Calls and results from plain turns (conv_id, turn, role, text).

    A user's turn calls `reply` and depends on the conversation's turn before; a system's turn calls `instruct`; the assistant's turn
    is the result of the turn before it. A message whose text is a JSON object with `tool_calls` (each with id, name, arguments and
    perhaps depends_on) makes those calls, and one of role `tool` with `id` and `content` is that result.
    """
    parsed = "struct<tool_calls:array<struct<id:string,name:string,arguments:string,depends_on:array<string>>>,id:string,content:string>"
    m = messages.select("conv_id", "turn", "role", "text", F.when(F.col("text").startswith("{"), F.from_json("text", parsed)).alias("j"))
    words = F.coalesce(F.regexp_count("text", F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0))
    name = lambda back: F.concat(F.lit("t"), (F.col("turn") - back).cast("string"))
    args = F.when(F.col("role") == "user", F.to_json(F.struct(F.col("text").alias("prompt"), words.alias("words")))).otherwise(F.to_json(F.struct(F.col("text").alias("rule"))))
    plain = m.where("role in ('user', 'system') and (j is null or j.tool_calls is null)")
    calls = plain.select("conv_id", "turn", name(0).alias("call_id"), F.when(F.col("role") == "user", "reply").otherwise("instruct").alias("name"), args.alias("arguments"), F.when((F.col("role") == "user") & (F.col("turn") > 0), F.array(name(1), name(2))).otherwise(F.array().cast("array<string>")).alias("depends_on"))
    own = m.where("j.tool_calls is not null").select("conv_id", "turn", F.explode("j.tool_calls").alias("c")).select("conv_id", "turn", F.col("c.id").alias("call_id"), F.col("c.name").alias("name"), F.col("c.arguments").alias("arguments"), F.col("c.depends_on").alias("depends_on"))
    replies = m.where("role = 'assistant' and (j is null or j.tool_calls is null)").select("conv_id", "turn", name(1).alias("call_id"), F.col("text").alias("content"))
    tool = m.where("role = 'tool'").select("conv_id", "turn", F.col("j.id").alias("call_id"), F.col("j.content").alias("content"))
    return calls.unionByName(own), replies.unionByName(tool)
