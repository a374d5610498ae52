"""Chat formatting with tool calls linked to their results.

A message of the assistant may hold calls, as JSON {"content": ..., "tool_calls": [{"id", "name", "arguments",
"after"}]}, and a message of role "tool" the result of one, as JSON {"tool_call_id", "content"}. Calls and results of
a conversation are hash-joined by identifier; arguments are validated against the tool's schema; every message, call
and result becomes one record of canonical JSON (sorted keys, no blanks, shortest numbers).

The order is topological: a result comes after its call, and a call after the results of the calls that it names
("after", or a string argument "$id"). Each record gets the key (order_turn, order_depth, turn, part), the least one
that respects this and the turns; keys spread along dependencies, a round for each link of the longest chain. Records
of a cycle keep their own turn and say so. A conversation is never gathered: its records sort by their keys.

``derived`` makes calls and results of plain conversations, which hold none.

Cases: null texts are empty content, null turns come first; text that isn't the JSON above, or nests deeper than
``MOST_DEPTH``, is plain content; numbers that aren't finite are null in records and fit no number type; halves of
surrogate pairs are written as escapes; a name that isn't a string is an unknown tool; an
identifier used several times links its n-th call to its n-th result; calls without result and results without call
stay and have no link; equal rows are records each; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import json
import math
import re

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import slices, written

NODES = "conv_id long, turn long, part int, kind string, ident string, after array<string>, valid boolean, errors array<string>, record string"
#: The deepest nesting of JSON that is read as such.
MOST_DEPTH = 100
HALVES = re.compile("[\ud800-\udfff]")
TYPES = {"object": dict, "array": list, "string": str, "boolean": bool, "null": type(None)}


def canonical(value) -> str:
    """Canonical JSON of a parsed value."""
    if isinstance(value, dict):
        keys = sorted(value, key=lambda k: k.encode("utf-16-be", "surrogatepass"))
        return "{" + ",".join(f"{canonical(k)}:{canonical(value[k])}" for k in keys) + "}"
    if isinstance(value, list):
        return "[" + ",".join(map(canonical, value)) + "]"
    if isinstance(value, float):
        if not math.isfinite(value):
            return "null"
        return str(int(value)) if value == int(value) and abs(value) < 1e21 else repr(value).replace("e-0", "e-").replace("e+0", "e+")
    return whole(json.dumps(value, ensure_ascii=False))


def whole(text: str) -> str:
    """The text with halves of surrogate pairs as escapes, so that it has a UTF-8 form."""
    return HALVES.sub(lambda m: f"\\u{ord(m[0]):04x}", text)


def problems(value, schema: dict, path: str = "$") -> list[str]:
    """What contradicts a JSON schema: type, enum, const, required, properties, additionalProperties, items, ranges, lengths."""
    found: list[str] = []
    kinds = schema.get("type")
    if kinds is not None:
        kinds = kinds if isinstance(kinds, list) else [kinds]
        number = isinstance(value, (int, float)) and not isinstance(value, bool) and math.isfinite(value)
        fits = any(number and (k == "number" or value == int(value)) if k in ("number", "integer") else isinstance(value, TYPES.get(k, ())) for k in kinds)
        if not fits:
            return [f"{path}: not {' or '.join(kinds)}"]
    if "enum" in schema and value not in schema["enum"]:
        found.append(f"{path}: not in enum")
    if "const" in schema and value != schema["const"]:
        found.append(f"{path}: not the constant")
    if isinstance(value, dict):
        own = schema.get("properties", {})
        found += [f"{path}: {name} is missing" for name in schema.get("required", ()) if name not in value]
        rest = schema.get("additionalProperties", True)
        for name, item in value.items():
            if name in own:
                found += problems(item, own[name], f"{path}.{name}")
            elif rest is False:
                found.append(f"{path}: {name} is not allowed")
            elif isinstance(rest, dict):
                found += problems(item, rest, f"{path}.{name}")
    elif isinstance(value, list):
        if isinstance(schema.get("items"), dict):
            found += [p for i, item in enumerate(value) for p in problems(item, schema["items"], f"{path}[{i}]")]
        if len(value) < schema.get("minItems", 0) or len(value) > schema.get("maxItems", len(value)):
            found.append(f"{path}: number of items")
    elif isinstance(value, str):
        if len(value) < schema.get("minLength", 0) or len(value) > schema.get("maxLength", len(value)):
            found.append(f"{path}: length")
    elif isinstance(value, (int, float)) and not isinstance(value, bool):
        if value < schema.get("minimum", value) or value > schema.get("maximum", value):
            found.append(f"{path}: out of range")
    return found


def _loaded(text: str):
    try:
        value = json.loads(text)
    except (ValueError, RecursionError):
        return None
    level, depth = [value], 0
    while level:
        level = [x for v in level for x in (v.values() if isinstance(v, dict) else v if isinstance(v, list) else ())]
        depth += 1
        if depth > MOST_DEPTH:
            return None
    return value if isinstance(value, dict) else None


def _references(value) -> list[str]:
    if isinstance(value, str):
        return [value[1:]] if value.startswith("$") and len(value) > 1 else []
    items = value.values() if isinstance(value, dict) else value if isinstance(value, list) else ()
    return [x for item in items for x in _references(item)]


def parse(conv: int | None, turn: int | None, role: str | None, text: str | None, schemas: dict[str, dict]) -> list[tuple]:
    """The records of one message, as rows of NODES without conversation and turn."""
    base = {"conv_id": conv, "turn": turn}
    value = _loaded(text) if text and text.lstrip()[:1] == "{" and role in ("assistant", "tool") else None
    if role == "tool" and value is not None and isinstance(value.get("tool_call_id"), str):
        ident = whole(value["tool_call_id"])
        record = base | {"kind": "result", "id": ident, "content": value.get("content")}
        return [(0, "result", ident, [], None, [], canonical(record))]
    calls = value.get("tool_calls") if value is not None and role == "assistant" else None
    if not isinstance(calls, list):
        return [(0, "message", None, [], None, [], canonical(base | {"kind": "message", "role": role, "content": text or ""}))]
    rows = [(0, "message", None, [], None, [], canonical(base | {"kind": "message", "role": role, "content": value.get("content") or ""}))]
    for part, call in enumerate(calls, 1):
        call = call if isinstance(call, dict) else {}
        ident, name, arguments = call.get("id"), call.get("name"), call.get("arguments", {})
        if isinstance(arguments, str):
            arguments = _loaded(arguments)
        errors = [] if isinstance(arguments, dict) else ["$: arguments are no object"]
        if not isinstance(name, str) or name not in schemas:
            errors.append("unknown tool")
        elif not errors:
            errors = problems(arguments, schemas[name])
        named = call.get("after")
        after = sorted({whole(x) for x in [*(y for y in (named if isinstance(named, list) else []) if isinstance(y, str)), *_references(arguments)]})
        ident = whole(ident) if isinstance(ident, str) else None
        errors = [whole(x) for x in errors]
        record = base | {"kind": "call", "id": ident, "name": name, "arguments": arguments, "valid": not errors}
        rows.append((part, "call", ident, after, not errors, errors, canonical(record)))
    return rows


def nodes(messages: DataFrame, schemas: dict[str, dict]) -> DataFrame:
    def task(batches):
        import pyarrow as pa

        types = (pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.string(), pa.list_(pa.string()), pa.bool_(), pa.list_(pa.string()), pa.string())
        names = [x.split()[0] for x in NODES.split(", ")]
        for batch in slices(batches):
            out = [(conv, turn, *row) for conv, turn, role, text in zip(*(batch.column(i).to_pylist() for i in range(4))) for row in parse(conv, turn, role, text, schemas)]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names)

    rows = messages.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text")
    return rows.mapInArrow(task, NODES)


def format_chats(messages: DataFrame, schemas: dict[str, dict] | None = None) -> DataFrame:
    """Records of messages (conv_id, turn, role, text): conv_id, turn, part, kind, order_turn, order_depth, linked_turn
    (of a call's result, of a result's call), valid, errors, cyclic, record."""
    found = written(nodes(messages, schemas or {}).withColumn("id", F.monotonically_increasing_id()), "chat-nodes")
    order = Window.partitionBy("conv_id", "ident", "kind").orderBy("turn", "part", "id")
    named = found.filter("ident IS NOT NULL").withColumn("nth", F.row_number().over(order)).select("conv_id", "ident", "kind", "nth", "turn", "id")
    calls = named.filter("kind = 'call'").select("conv_id", "ident", "nth", F.col("id").alias("call"), F.col("turn").alias("call_turn"))
    results = named.filter("kind = 'result'").select(F.col("conv_id").alias("_c"), F.col("ident").alias("_i"), F.col("nth").alias("_n"), F.col("id").alias("result"), F.col("turn").alias("result_turn"))
    same = F.col("conv_id").eqNullSafe(F.col("_c")) & (F.col("ident") == F.col("_i")) & (F.col("nth") == F.col("_n"))
    links = written(calls.join(results.hint("shuffle_hash"), same).select("conv_id", "ident", "nth", "call", "call_turn", "result", "result_turn"), "chat-links")
    # Edges from what must come first: call to result, and the (first) result of a named call to the call that needs it.
    needs = found.filter("kind = 'call' AND size(after) > 0").select(F.col("conv_id").alias("_c"), F.col("id").alias("later"), F.explode("after").alias("_i"))
    first = links.filter("nth = 1").select("conv_id", "ident", "result")
    edges = links.select(F.col("call").alias("earlier"), F.col("result").alias("later"))
    edges = edges.unionByName(needs.join(first, F.col("conv_id").eqNullSafe(F.col("_c")) & (F.col("ident") == F.col("_i"))).select(F.col("result").alias("earlier"), "later").distinct())
    edges = written(edges, "chat-edges")
    keys = order_keys(found.select("id", "turn"), edges)
    turns = links.select(F.col("call").alias("id"), F.col("result_turn").alias("linked_turn")).unionByName(links.select(F.col("result").alias("id"), F.col("call_turn").alias("linked_turn")))
    done = found.join(keys, "id", "left").join(turns, "id", "left")
    return done.select(
        "conv_id", "turn", "part", "kind", F.coalesce("order_turn", "turn").alias("order_turn"), F.coalesce("order_depth", F.lit(0)).alias("order_depth"),
        "linked_turn", "valid", "errors", F.coalesce("cyclic", F.lit(False)).alias("cyclic"), "record",
    )


def order_keys(rows: DataFrame, edges: DataFrame) -> DataFrame:
    """id, order_turn, order_depth, cyclic of the rows that edges touch: (turn, 0), or one deeper than the greatest key before it."""
    touched = edges.select(F.col("earlier").alias("id")).unionByName(edges.select(F.col("later").alias("id"))).distinct()
    rows = written(rows.join(touched, "id", "left_semi"), "chat-ordered")
    waiting = rows.join(edges.select(F.col("later").alias("id")).distinct(), "id", "left_semi")
    done = written(rows.join(waiting, "id", "left_anti").select("id", F.col("turn").alias("order_turn"), F.lit(0).alias("order_depth"), F.lit(False).alias("cyclic")), "chat-keys")
    waiting = written(waiting, "chat-waiting")
    while not waiting.isEmpty():
        before = edges.join(done.select(F.col("id").alias("earlier"), F.struct("order_turn", "order_depth").alias("key")), "earlier", "left")
        ready = before.groupBy(F.col("later").alias("id")).agg(F.max("key").alias("key"), F.count(F.when(F.col("key").isNull(), 1)).alias("open")).filter("open = 0")
        step = waiting.join(ready, "id").select(
            "id",
            F.greatest("turn", F.col("key.order_turn")).alias("order_turn"),
            F.when(F.coalesce(F.col("turn") > F.col("key.order_turn"), F.lit(False)), 0).otherwise(F.col("key.order_depth") + 1).alias("order_depth"),
            F.lit(False).alias("cyclic"),
        )
        step = written(step, "chat-step")
        if step.isEmpty():
            # Only cycles, and what waits for them, are left.
            return done.unionByName(waiting.select("id", F.col("turn").alias("order_turn"), F.lit(0).alias("order_depth"), F.lit(True).alias("cyclic")))
        done = done.unionByName(step)
        waiting = written(waiting.join(step, "id", "left_anti"), "chat-waiting")
    return done


def derived(messages: DataFrame) -> DataFrame:
    """Plain conversations with a tool call for each question that is answered.

    All messages stay. A message of the user at turn t with one of the assistant at turn t + 1 also becomes a call of
    the tool "search" at turn t, with the identifier "c" and t, and the answer becomes its result at turn t + 1. Where
    t / 2 rounded down is even, the call needs the result of the call of turn t + 2, if there is one, so the order
    differs from that of the turns."""
    turn = F.col("turn").cast("long")
    rows = messages.select("conv_id", turn.alias("turn"), "role", "text")
    keys = lambda role, step: rows.filter(F.col("role") == role).select("conv_id", (F.col("turn") + step).alias("turn")).distinct()
    asked = rows.filter("role = 'user'").join(keys("assistant", -1), ["conv_id", "turn"], "left_semi")
    answers = rows.filter("role = 'assistant'").join(keys("user", 1), ["conv_id", "turn"], "left_semi")
    ident = lambda step: F.concat(F.lit("c"), (F.col("turn") + step).cast("string"))
    after = F.when(F.expr("turn div 2 % 2 = 0"), F.array(ident(2))).otherwise(F.array())
    arguments = F.struct(F.length("text").alias("limit"), F.col("text").alias("query"))
    call = F.struct(ident(0).alias("id"), F.lit("search").alias("name"), arguments.alias("arguments"), after.alias("after"))
    calls = asked.select("conv_id", "turn", F.lit("assistant").alias("role"), F.to_json(F.struct(F.array(call).alias("tool_calls"))).alias("text"))
    result = F.struct(ident(-1).alias("tool_call_id"), F.col("text").alias("content"))
    results = answers.select("conv_id", "turn", F.lit("tool").alias("role"), F.to_json(result, {"ignoreNullFields": "false"}).alias("text"))
    return rows.unionByName(calls).unionByName(results)


CHAT_SQL = """
WITH messages AS (SELECT conv_id, turn, role, text, text IS NOT NULL AND length(text) BETWEEN 1 AND 200 AS fits FROM conversations),
asked AS (SELECT q.conv_id, q.turn, q.text, q.fits, a.text AS answer FROM messages q JOIN messages a ON a.conv_id = q.conv_id AND a.turn = q.turn + 1
  WHERE q.role = 'user' AND a.role = 'assistant'),
-- A call that needs a later result comes right after it, and its own result after the call.
moved AS (SELECT x.*, y.turn + 1 AS needed FROM asked x LEFT JOIN asked y ON y.conv_id = x.conv_id AND y.turn = x.turn + 2 AND x.turn // 2 % 2 = 0)
SELECT conv_id, turn, 0 AS part, 'message' AS kind, turn AS order_turn, 0 AS order_depth, NULL::BIGINT AS linked_turn, NULL::BOOLEAN AS valid, false AS cyclic,
  '{"content":' || to_json(coalesce(text, ''))::VARCHAR || ',"conv_id":' || conv_id || ',"kind":"message","role":' || to_json(role)::VARCHAR || ',"turn":' || turn || '}' AS record
FROM messages
UNION ALL
SELECT conv_id, turn, 0, 'message', turn, 0, NULL, NULL, false, '{"content":"","conv_id":' || conv_id || ',"kind":"message","role":"assistant","turn":' || turn || '}' FROM moved
UNION ALL
SELECT conv_id, turn, 1, 'call', coalesce(needed, turn), CASE WHEN needed IS NULL THEN 0 ELSE 1 END, turn + 1, fits, false,
  '{"arguments":{' || coalesce('"limit":' || length(text) || ',"query":' || to_json(text)::VARCHAR, '') || '},"conv_id":' || conv_id || ',"id":"c' || turn
    || '","kind":"call","name":"search","turn":' || turn || ',"valid":' || fits || '}' FROM moved
UNION ALL
SELECT conv_id, turn + 1, 0, 'result', coalesce(needed, turn + 1), CASE WHEN needed IS NULL THEN 0 ELSE 2 END, turn, NULL, false,
  '{"content":' || coalesce(to_json(answer)::VARCHAR, 'null') || ',"conv_id":' || conv_id || ',"id":"c' || turn || '","kind":"result","turn":' || turn + 1 || '}' FROM moved
"""
