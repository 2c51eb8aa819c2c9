"""Chat formatting: tool calls and results, linked by identifier, ordered, validated, in canonical JSON.

A message whose text is a JSON object with ``tool_calls`` (a list of objects with id, name and arguments) holds calls beside its
optional ``content``; a message of role ``tool`` whose text is a JSON object with ``tool_call_id`` is a result. Everything else
is a plain message. An argument of the form {"$result": "<call id>"} makes a call depend on that call's result.

Linking is a hash join of results to calls on (conversation, identifier), with one call per identifier: the first by
turn and index. Order is topological: an event's place is (turn, level, index, step), where a call that depends on
another comes at or after that call's turn and on a later level, and a result follows its call. The places are keys to sort by,
found without bringing a conversation into one task. Arguments are checked against JSON schemas (a documented part:
type, properties, required, additionalProperties, enum, const, items, minimum, maximum, minLength, maxLength, pattern).

Status of an event: message; call: ok, invalid (arguments fail their schema), unknown_tool, duplicate (identifier used before),
unanswered (no result), cyclic (depends on itself) and missing (depends on a call that is not there); result: ok, orphan.
A call gets the first that holds of duplicate, unknown_tool, invalid, missing, cyclic, unanswered, ok.

Edge cases: null text is empty content, a null role is JSON null, a null conv_id is a conversation of its own and a null
turn comes before all others; repeated rows give repeated events; broken JSON is a plain message, as is JSON with numbers that
are not finite, with half a surrogate pair, or nested deeper than 100 levels; whole numbers may be of any size; an empty table
gives no rows; other columns are ignored.
"""

from __future__ import annotations

import json
import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.llm.common import bounded_batches, discard, join_hot, materialise, read_table

EVENT = "conv_id {conv}, turn {turn}, idx int, kind string, role string, call_id string, name string, body string, problem string, refs array<string>"
#: JSON nested deeper than this is a plain message.
DEEPEST = 100
#: Tools that the query knows.
TOOLS = {
    "search": {"type": "object", "properties": {"query": {"type": "string", "minLength": 1}, "limit": {"type": "integer", "minimum": 1, "maximum": 100}}, "required": ["query"], "additionalProperties": False},
    "calculate": {"type": "object", "properties": {"expression": {"type": "string"}}, "required": ["expression"], "additionalProperties": False},
}


def canonical(value) -> str:
    """JSON with sorted keys, no spaces, whole floats as integers, characters as they are."""

    def plain(v):
        if isinstance(v, float) and v.is_integer() and abs(v) < 2**53:
            return int(v)
        if isinstance(v, dict):
            return {k: plain(x) for k, x in v.items()}
        return [plain(x) for x in v] if isinstance(v, list) else v

    return json.dumps(plain(value), sort_keys=True, separators=(",", ":"), ensure_ascii=False, allow_nan=False)


def strict(text: str):
    """Parsed JSON, or None where it is broken, holds numbers that are not finite or half a surrogate pair, or is nested deeper than DEEPEST."""

    def refuse(name):
        raise ValueError(name)

    def finite(digits):
        return found if math.isfinite(found := float(digits)) else refuse(digits)

    try:
        value = json.loads(text, parse_constant=refuse, parse_float=finite)
        level = [value]
        for _ in range(DEEPEST):
            level = [x for v in level if isinstance(v, (dict, list)) for x in (v.values() if isinstance(v, dict) else v)]
        if any(isinstance(v, (dict, list)) for v in level):
            return None
        canonical(value).encode()
        return value
    except (ValueError, RecursionError):
        return None


def problem_of(value, schema: dict, at: str = "$") -> str | None:
    """The first violation of the schema, or None; references to results pass."""
    import re

    if isinstance(value, dict) and set(value) == {"$result"}:
        return None
    kinds = {"object": dict, "array": list, "string": str, "boolean": bool, "null": type(None)}
    kind = schema.get("type")
    number = isinstance(value, (int, float)) and not isinstance(value, bool)
    if kind in kinds and not isinstance(value, kinds[kind]) or kind == "number" and not number or kind == "integer" and not (number and (isinstance(value, int) or value.is_integer())):
        return f"{at}: not of type {kind}"
    if "enum" in schema and value not in schema["enum"] or "const" in schema and value != schema["const"]:
        return f"{at}: not an allowed value"
    if number and (value < schema.get("minimum", value) or value > schema.get("maximum", value)):
        return f"{at}: out of range"
    if isinstance(value, str):
        if not schema.get("minLength", 0) <= len(value) <= schema.get("maxLength", len(value)):
            return f"{at}: wrong length"
        if "pattern" in schema and not re.search(schema["pattern"], value):
            return f"{at}: no match for the pattern"
    if isinstance(value, dict):
        for name in schema.get("required", []):
            if name not in value:
                return f"{at}.{name}: missing"
        for name, x in sorted(value.items()):
            inner = schema.get("properties", {}).get(name)
            if inner is None and schema.get("additionalProperties") is False:
                return f"{at}.{name}: not allowed"
            if inner and (found := problem_of(x, inner, f"{at}.{name}")):
                return found
    if isinstance(value, list) and "items" in schema:
        return next((p for i, x in enumerate(value) if (p := problem_of(x, schema["items"], f"{at}[{i}]"))), None)
    return None


def references(value) -> list[str]:
    if isinstance(value, dict):
        if set(value) == {"$result"} and isinstance(value["$result"], str):
            return [value["$result"]]
        return sorted({r for x in value.values() for r in references(x)})
    return sorted({r for x in value for r in references(x)}) if isinstance(value, list) else []


def events_of(role: str | None, text: str | None, tools: dict) -> list[tuple]:
    """Events (idx, kind, role, call_id, name, body, problem, refs) of one message."""
    found = strict(text) if text and text.lstrip()[:1] == "{" else None
    if isinstance(found, dict) and role == "tool" and isinstance(found.get("tool_call_id"), str):
        body = canonical({"role": "tool", "tool_call_id": found["tool_call_id"], "content": found.get("content")})
        return [(0, "result", role, found["tool_call_id"], None, body, None, [])]
    calls = found.get("tool_calls") if isinstance(found, dict) else None
    if not isinstance(calls, list) or not calls or not all(isinstance(c, dict) and isinstance(c.get("id"), str) and isinstance(c.get("name"), str) for c in calls):
        return [(0, "message", role, None, None, canonical({"role": role, "content": text or ""}), None, [])]
    out = [(0, "message", role, None, None, canonical({"role": role, "content": found["content"]}), None, [])] if found.get("content") is not None else []
    for i, c in enumerate(calls, 1):
        given = c.get("arguments", {})
        given = strict(given) if isinstance(given, str) else given
        problem = "unknown tool" if c["name"] not in tools else problem_of(given, tools[c["name"]])
        body = canonical({"role": role, "tool_call": {"id": c["id"], "name": c["name"], "arguments": given}})
        out.append((i, "call", role, c["id"], c["name"], body, problem, references(given)))
    return out


def events(messages: DataFrame, tools: dict) -> DataFrame:
    bounded_batches(messages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, out = [], []
            for i, (role, text) in enumerate(zip(b.column(2).to_pylist(), b.column(3).to_pylist())):
                for e in events_of(role, text, tools):
                    rows.append(i)
                    out.append(e)
            cols = list(zip(*out)) or [[]] * 8
            kinds = [pa.int32(), *[pa.string()] * 6, pa.list_(pa.string())]
            at = pa.array(rows, pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0).take(at), b.column(1).take(at), *(pa.array(c, t) for c, t in zip(cols, kinds))], names=["conv_id", "turn", "idx", "kind", "role", "call_id", "name", "body", "problem", "refs"])

    kind = {k: messages.schema[c].dataType.simpleString() for k, c in (("conv", "conv_id"), ("turn", "turn"))}
    return messages.select("conv_id", "turn", "role", "text").mapInArrow(run, EVENT.format(**kind))


def places(calls: DataFrame) -> DataFrame:
    """For calls(ck, call_id, turn, refs), one per identifier: ck, call_id, at (turn), level, missing and cyclic.

    Each round moves every dependent call behind what it depends on; calls that still move after as many rounds as there
    are dependent calls, or depend on such, are on a cycle.
    """
    deps = calls.select("ck", "call_id", F.explode("refs").alias("need")).distinct()
    start = calls.select("ck", "call_id", F.coalesce("turn", F.lit(-1)).cast("long").alias("at"), F.lit(0).alias("level"))
    none = start.withColumns({"missing": F.lit(False), "cyclic": F.lit(False)})
    deps = materialise(deps, "chat-deps")
    if deps.isEmpty():
        return none
    there = calls.select("ck", F.col("call_id").alias("need"))
    missing = deps.join(there, ["ck", "need"], "left_anti").select("ck", "call_id").distinct().withColumn("missing", F.lit(True))
    deps = materialise(deps.join(there, ["ck", "need"]), "chat-deps-there")
    # peel: calls all of whose needs are placed get their place; what never gets one is on or behind a cycle
    free = deps.select("ck", "call_id").distinct()
    done = materialise(start.join(free, ["ck", "call_id"], "left_anti"), "chat-placed")
    waiting = materialise(start.drop("level").join(free, ["ck", "call_id"]), "chat-waiting")
    while not waiting.isEmpty():
        needs = deps.join(waiting.select("ck", "call_id"), ["ck", "call_id"], "left_semi").join(done.select("ck", F.col("call_id").alias("need"), F.col("at").alias("need_at"), F.col("level").alias("need_level")), ["ck", "need"], "left")
        ready = needs.groupBy("ck", "call_id").agg(F.bool_and(F.col("need_at").isNotNull()).alias("ready"), F.max(F.struct("need_at", "need_level")).alias("last")).filter("ready")
        placed = waiting.join(ready, ["ck", "call_id"]).select("ck", "call_id", F.greatest("at", "last.need_at").alias("new_at"), F.when(F.col("last.need_at") >= F.col("at"), F.col("last.need_level") + 1).otherwise(0).alias("level"))
        placed = materialise(placed.select("ck", "call_id", F.col("new_at").alias("at"), "level"), "chat-placed")
        if placed.isEmpty():
            break
        spent = (done, waiting, placed)
        done = materialise(done.unionByName(placed), "chat-placed")
        waiting = materialise(waiting.join(placed, ["ck", "call_id"], "left_anti"), "chat-waiting")
        discard(*spent)
    stuck = waiting.withColumns({"level": F.lit(0), "cyclic": F.lit(True)})
    both = done.withColumn("cyclic", F.lit(False)).unionByName(stuck.select("ck", "call_id", "at", "level", "cyclic"))
    return both.join(missing, ["ck", "call_id"], "left").withColumn("missing", F.coalesce("missing", F.lit(False)))


def format_chat(messages: DataFrame, tools: dict | None = None) -> DataFrame:
    """Events of all messages: conv_id, turn, idx, kind, status, problem, at, level, step and the canonical json.

    Sorting by (conv_id, at, level, turn, idx, step) gives each conversation in topological order.
    """
    every = materialise(events(messages, TOOLS if tools is None else tools).withColumn("ck", F.coalesce(F.concat(F.lit("c"), F.col("conv_id").cast("string")), F.lit("n"))), "chat-events")
    key = ["ck", "call_id"]
    calls = every.filter("kind = 'call'")
    results = every.filter("kind = 'result'")
    answers = results.groupBy(*key).agg(F.count("*").alias("n"))
    first = calls.groupBy(*key).agg(F.min(F.struct("turn", "idx")).alias("first"), F.min_by("refs", F.struct("turn", "idx")).alias("refs"), F.count("*").alias("n_calls"))
    first = materialise(first.join(answers, key, "left").withColumn("n", F.coalesce("n", F.lit(0))), "chat-calls")
    placed = places(first.select("ck", "call_id", F.col("first.turn").alias("turn"), "refs"))
    known = materialise(first.drop("refs").join(placed, key), "chat-places")
    again = ~(F.col("turn").eqNullSafe(F.col("first.turn")) & F.col("idx").eqNullSafe(F.col("first.idx")))
    status = F.when(again, "duplicate").when(F.col("problem") == "unknown tool", "unknown_tool").when(F.col("problem").isNotNull(), "invalid")
    status = status.when(F.col("missing"), "missing").when(F.col("cyclic"), "cyclic").when(F.col("n") == 0, "unanswered").otherwise("ok")
    shape = ["conv_id", "turn", "idx", "kind", "status", "problem", "at", "level", "step", "json"]
    own_turn = F.coalesce("turn", F.lit(-1)).cast("long")
    total = every.count()
    linked_calls = join_hot(calls, known, key, "n_calls", total).select("conv_id", "turn", "idx", "kind", status.alias("status"), "problem", F.when(again, own_turn).otherwise(F.col("at")).alias("at"), F.when(again, 0).otherwise(F.col("level")).alias("level"), F.lit(0).alias("step"), F.col("body").alias("json"))
    with_call = join_hot(results.select("ck", "call_id", "conv_id", F.col("turn").alias("own"), "idx", "kind", "body"), known.select("ck", "call_id", "first", "at", "level", "n"), key, "n", total, how="left")
    linked_results = with_call.select("conv_id", F.col("own").alias("turn"), "idx", "kind", F.when(F.col("at").isNull(), "orphan").otherwise("ok").alias("status"), F.lit(None).cast("string").alias("problem"), F.coalesce(F.col("at"), F.col("own").cast("long"), F.lit(-1)).alias("at"), F.coalesce("level", F.lit(0)).alias("level"), F.when(F.col("at").isNull(), 0).otherwise(1).alias("step"), F.col("body").alias("json"))
    plain = every.filter("kind = 'message'").select("conv_id", "turn", "idx", "kind", F.lit("message").alias("status"), "problem", own_turn.alias("at"), F.lit(0).alias("level"), F.lit(0).alias("step"), F.col("body").alias("json"))
    return plain.select(*shape).unionByName(linked_calls.select(*shape)).unionByName(linked_results.select(*shape))


def as_tool_chat(messages: DataFrame) -> DataFrame:
    """Conversations as calls and results, by a fixed rule on turn and length, for tables that hold none; (conv_id, turn, role, text).

    A message of an assistant becomes a call of the identifier c0 to c5 for its turn, with the whole text, or a reference two turns on or
    back, as its query; a user's message after turn 0 becomes the result for the turn before. So there are calls that
    are answered, unanswered, invalid, unknown, missing something, cyclic, or repeat an identifier. Other rows stay.
    """
    size = F.coalesce(F.length("text"), F.lit(0))
    name = lambda turn: F.concat(F.lit("c"), F.pmod(turn, F.lit(6)).cast("string"))
    turn, limit = F.col("turn").cast("long"), (size % 110).alias("limit")
    there = F.when(size % 4 == 1, name(turn + 2)).when((size % 4 == 2) & (turn >= 3), name(turn - 2))
    linked = F.to_json(F.struct(limit, F.struct(there.alias("$result")).alias("query")))
    given = F.when(there.isNotNull(), linked).otherwise(F.to_json(F.struct(limit, F.coalesce("text", F.lit("")).alias("query"))))
    call = F.struct(name(turn).alias("id"), F.when(size % 7 == 0, "lookup").otherwise("search").alias("name"), given.alias("arguments"))
    asked = F.to_json(F.struct(F.when(size % 3 == 0, F.coalesce("text", F.lit(""))).alias("content"), F.array(call).alias("tool_calls")))
    answer = F.to_json(F.struct(name(turn - 1).alias("tool_call_id"), F.coalesce("text", F.lit("")).alias("content")))
    calls, answers = (F.col("role") == "assistant") & turn.isNotNull(), (F.col("role") == "user") & (turn > 0)
    return messages.select("conv_id", "turn", F.when(answers, "tool").otherwise(F.col("role")).alias("role"), F.when(calls, asked).when(answers, answer).otherwise(F.col("text")).alias("text"))


def digested(done: DataFrame) -> DataFrame:
    return done.select("conv_id", "turn", "idx", "kind", "status", "at", "level", "step", F.octet_length("json").cast("long").alias("json_bytes"), F.sha2("json", 256).alias("json_sha256"))


def op3_tool_links(spark, sf_dir: str) -> DataFrame:
    """All conversations as calls and results, linked, ordered and validated; the JSON by length and digest."""
    return digested(format_chat(as_tool_chat(read_table(spark, sf_dir, "conversations"))))


def chat_messages(spark, sf_dir: str) -> DataFrame:
    """All conversations as they are given: plain messages."""
    return digested(format_chat(read_table(spark, sf_dir, "conversations")))


MESSAGES_SQL = """
WITH m AS (SELECT conv_id, turn, '{"content":' || to_json(coalesce(text, ''))::VARCHAR || ',"role":' || coalesce(to_json(role)::VARCHAR, 'null') || '}' AS j FROM conversations)
SELECT conv_id, turn, 0::INT AS idx, 'message' AS kind, 'message' AS status, coalesce(turn, -1)::BIGINT AS at, 0::INT AS level, 0::INT AS step,
       octet_length(encode(j))::BIGINT AS json_bytes, sha256(j) AS json_sha256 FROM m
"""
#: The rule of as_tool_chat and what follows from it: a call has one need at most, so places come from one recursion.
OP3_SQL = """
WITH RECURSIVE m AS (SELECT conv_id, turn, role, coalesce(text, '') AS t, length(coalesce(text, '')) AS n, role = 'assistant' AND turn IS NOT NULL AS asks, role = 'user' AND turn > 0 AS answers FROM conversations),
calls AS (
  SELECT *, 'c' || (turn % 6) AS id, CASE WHEN n % 4 = 1 THEN 'c' || ((turn + 2) % 6) WHEN n % 4 = 2 AND turn >= 3 THEN 'c' || ((turn - 2) % 6) END AS need,
         row_number() OVER (PARTITION BY conv_id, turn % 6 ORDER BY turn) AS nth FROM m WHERE asks),
heads AS (SELECT conv_id, id, turn, need FROM calls WHERE nth = 1),
wired AS (SELECT h.*, p.id AS met FROM heads h LEFT JOIN heads p ON h.conv_id IS NOT DISTINCT FROM p.conv_id AND h.need = p.id),
placed(conv_id, id, spot, level) AS (
  SELECT conv_id, id, turn, 0 FROM wired WHERE met IS NULL
  UNION ALL
  SELECT w.conv_id, w.id, greatest(w.turn, p.spot), CASE WHEN p.spot >= w.turn THEN p.level + 1 ELSE 0 END FROM wired w JOIN placed p ON w.conv_id IS NOT DISTINCT FROM p.conv_id AND w.met = p.id),
known AS (
  SELECT w.conv_id, w.id, w.need IS NOT NULL AND w.met IS NULL AS missing, p.id IS NULL AS cyclic, coalesce(p.spot, w.turn) AS spot, coalesce(p.level, 0) AS level
  FROM wired w LEFT JOIN placed p ON w.conv_id IS NOT DISTINCT FROM p.conv_id AND w.id = p.id),
results AS (SELECT *, 'c' || ((turn - 1) % 6) AS id FROM m WHERE answers),
answered AS (SELECT DISTINCT conv_id, id FROM results),
events AS (
  SELECT c.conv_id, c.turn, 1 AS idx, 'call' AS kind,
         CASE WHEN nth > 1 THEN 'duplicate' WHEN n % 7 = 0 THEN 'unknown_tool' WHEN n % 110 NOT BETWEEN 1 AND 100 OR need IS NULL AND n = 0 THEN 'invalid'
              WHEN missing THEN 'missing' WHEN cyclic THEN 'cyclic' WHEN a.id IS NULL THEN 'unanswered' ELSE 'ok' END AS status,
         CASE WHEN nth > 1 THEN c.turn ELSE k.spot END AS spot, CASE WHEN nth > 1 THEN 0 ELSE k.level END AS level, 0 AS step,
         '{"role":"assistant","tool_call":{"arguments":{"limit":' || (n % 110) || ',"query":' || CASE WHEN need IS NULL THEN to_json(t)::VARCHAR ELSE '{"$result":"' || need || '"}' END
         || '},"id":"' || c.id || '","name":"' || CASE WHEN n % 7 = 0 THEN 'lookup' ELSE 'search' END || '"}}' AS j
  FROM calls c LEFT JOIN known k ON c.conv_id IS NOT DISTINCT FROM k.conv_id AND c.id = k.id LEFT JOIN answered a ON c.conv_id IS NOT DISTINCT FROM a.conv_id AND c.id = a.id
  UNION ALL
  SELECT conv_id, turn, 0, 'message', 'message', turn, 0, 0, '{"content":' || to_json(t)::VARCHAR || ',"role":"assistant"}' FROM calls WHERE n % 3 = 0
  UNION ALL
  SELECT r.conv_id, r.turn, 0, 'result', CASE WHEN k.id IS NULL THEN 'orphan' ELSE 'ok' END, coalesce(k.spot, r.turn), coalesce(k.level, 0), CASE WHEN k.id IS NULL THEN 0 ELSE 1 END,
         '{"content":' || to_json(t)::VARCHAR || ',"role":"tool","tool_call_id":"' || r.id || '"}'
  FROM results r LEFT JOIN known k ON r.conv_id IS NOT DISTINCT FROM k.conv_id AND r.id = k.id
  UNION ALL
  SELECT conv_id, turn, 0, 'message', 'message', coalesce(turn, -1), 0, 0, '{"content":' || to_json(t)::VARCHAR || ',"role":' || coalesce(to_json(role)::VARCHAR, 'null') || '}'
  FROM m WHERE NOT coalesce(asks, FALSE) AND NOT coalesce(answers, FALSE))
SELECT conv_id, turn, idx::INT AS idx, kind, status, spot::BIGINT AS at, level::INT AS level, step::INT AS step, octet_length(encode(j))::BIGINT AS json_bytes, sha256(j) AS json_sha256 FROM events
"""
