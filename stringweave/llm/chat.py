"""Tool-call linking for chat formatting.

Events of a conversation are messages, calls and results.  A result meets its call in a
hash join on (conversation, identifier); repeated identifiers go to the first call and
the first result, the others are marked.  Calls are put in topological order of what
they depend on: where every dependency stands before its call, which one join shows,
the order of positions is already topological.  Other conversations are ordered whole, each
in a task's memory; those of more than GROUP_CALLS calls or dependencies, which no task should hold, are
peeled off in rounds until none is left.  Calls on a cycle, or above one, are marked.  Arguments
are validated against the tool's schema, and every event is serialised as canonical
JSON: keys sorted, no blanks, no escapes beyond those JSON needs.

Events without an identifier, and those of a null conversation, are linked to nothing
but still returned.  Null and empty bodies are empty objects for calls and null contents
for messages.  Repeated rows are returned as often as they are given.  An empty table gives no rows.
"""

from __future__ import annotations

import itertools
import json
import math
import re
from collections import defaultdict

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stringweave.llm._common import fields
from stringweave.session import Scratch

EVENTS = "conv_id long, pos long, kind string, name string, call_id string, after array<string>, body string"
#: JSON types that a schema may name.
TYPES = {"string": str, "integer": int, "number": (int, float), "boolean": bool, "array": list, "object": dict, "null": type(None)}
#: Calls, and dependencies, of one conversation that a task orders in its memory.
GROUP_CALLS = 10_000


def is_a(value, kind: str) -> bool:
    """Whether a value is of a JSON type; 1.0 is an integer, true is no number, a type of another name has no values."""
    if isinstance(value, bool) and kind in ("integer", "number"):
        return False
    return isinstance(value, TYPES.get(kind, ())) or kind == "integer" and isinstance(value, float) and value.is_integer()


def same(a, b) -> bool:
    """Equality of JSON values: 1 equals 1.0, true equals neither."""
    if isinstance(a, bool) or isinstance(b, bool):
        return a is b
    if isinstance(a, list) and isinstance(b, list):
        return len(a) == len(b) and all(map(same, a, b))
    if isinstance(a, dict) and isinstance(b, dict):
        return a.keys() == b.keys() and all(same(a[k], b[k]) for k in a)
    return a == b


def problems(value, schema: dict, at: str = "$") -> list[str]:
    """What is wrong with a value under a schema of type (a name or a list of names), properties, required, additionalProperties, items and enum."""
    kinds = schema.get("type")
    kinds = [kinds] if isinstance(kinds, str) else kinds
    if kinds and not any(is_a(value, k) for k in kinds):
        return [f"{at}: not {' or '.join(kinds)}"]
    if "enum" in schema and not any(same(value, x) for x in schema["enum"]):
        return [f"{at}: not in enum"]
    out = []
    if isinstance(value, dict):
        known = schema.get("properties", {})
        out += [f"{at}.{k}: missing" for k in schema.get("required", []) if k not in value]
        for k in sorted(value):
            if k in known:
                out += problems(value[k], known[k], f"{at}.{k}")
            elif schema.get("additionalProperties") is False:
                out.append(f"{at}.{k}: unknown")
    if isinstance(value, list) and "items" in schema:
        for i, v in enumerate(value):
            out += problems(v, schema["items"], f"{at}[{i}]")
    return out


def whole(text: str) -> str:
    """Text with lone surrogates, which UTF-8 can't hold, as JSON escapes."""
    return re.sub("[\ud800-\udfff]", lambda m: f"\\u{ord(m[0]):04x}", text)


def canonical(value) -> str:
    """Canonical JSON."""
    return whole(json.dumps(value, sort_keys=True, separators=(",", ":"), ensure_ascii=False))


def parsed(body: str):
    """The value of a JSON text; NaN, numbers beyond a double, repeated keys and nesting beyond Python's stack are refused."""

    def refuse(name: str):
        raise ValueError(name)

    def number(text: str) -> float:
        value = float(text)
        return value if math.isfinite(value) else refuse(text)

    def members(pairs: list) -> dict:
        value = dict(pairs)
        return value if len(value) == len(pairs) else refuse("repeated key")

    try:
        value = json.loads(body, parse_constant=refuse, parse_float=number, object_pairs_hook=members)
        json.dumps([[value]])  # it must also be writable, a little deeper than it stood
        return value
    except RecursionError as e:
        raise ValueError("nested too deeply") from e


def _key(c: str = "call_id") -> Column:
    """The identifier, or a key that equals no identifier and spreads evenly."""
    return F.coalesce(F.col(c), F.concat(F.lit("\0"), F.coalesce(F.col("pos").cast("string"), F.lit(""))))


def link(events: DataFrame) -> DataFrame:
    """Append ``partner`` (position of the first call or result of the identifier) and ``status``.

    Status: message, linked, repeated (a later call or result of an identifier already used),
    unanswered (a call without result) or orphan (a result without call).
    """
    e = events.withColumn("key", _key())
    named = e.where("call_id is not null and conv_id is not null")
    first = named.groupBy("conv_id", "key").agg(
        F.min(F.when(F.col("kind") == "call", F.col("pos"))).alias("call_pos"), F.min(F.when(F.col("kind") == "result", F.col("pos"))).alias("result_pos")
    )
    j = e.join(first.hint("shuffle_hash"), ["conv_id", "key"], "left")
    call, result = F.col("kind") == "call", F.col("kind") == "result"
    status = (
        F.when(~(call | result) | F.col("kind").isNull(), "message")
        .when(call & (F.col("pos") > F.col("call_pos")) | result & (F.col("pos") > F.col("result_pos")), "repeated")
        .when(call & F.col("result_pos").isNull(), "unanswered")
        .when(result & F.col("call_pos").isNull(), "orphan")
        .otherwise("linked")
    )
    partner = F.when(call, F.col("result_pos")).when(result, F.col("call_pos"))
    return j.select(*events.columns, partner.alias("partner"), status.alias("status"))


#: Rounds of peeling whose tables are read one by one; more are written as one.
ROUNDS_APART = 32


def order(calls: list[str], deps: list[tuple[str, str]]) -> dict[str, int]:
    """The longest chain of dependencies below each call, -1 on or above a cycle."""
    above, waits, depth = defaultdict(list), dict.fromkeys(calls, 0), {}
    for call, dep in deps:
        above[dep].append(call)
        waits[call] += 1
    front, at = [c for c in calls if not waits[c]], 0
    while front:
        depth |= dict.fromkeys(front, at)
        freed = []
        for c in front:
            for a in above[c]:
                waits[a] -= 1
                if not waits[a]:
                    freed.append(a)
        front, at = freed, at + 1
    return {c: depth.get(c, -1) for c in calls}


DEPTHS = "conv_id long, call_id string, depth int"


def _ordered(calls: pa.Table, deps: pa.Table) -> pa.Table:
    """One conversation's depths."""
    ids = calls["call_id"].to_pylist()
    found = order(ids, list(zip(deps["call_id"].to_pylist(), deps["dep"].to_pylist())))
    kinds = pa.schema([("conv_id", pa.int64()), ("call_id", pa.string()), ("depth", pa.int32())])
    return pa.table({"conv_id": calls["conv_id"], "call_id": ids, "depth": [found[c] for c in ids]}, schema=kinds)


def depths(events: DataFrame, max_rounds: int | None = None) -> DataFrame:
    """``(conv_id, call_id, depth)`` of calls in conversations where position is no topological order.

    ``depth`` is the longest chain of dependencies below a call, -1 on or above a cycle.  Other
    conversations have no rows; of repeated identifiers the first call counts.  ``max_rounds`` bounds
    the peeling of conversations above GROUP_CALLS; where it ends too early, it raises.
    """
    spark, store = events.sparkSession, Scratch(events.sparkSession, "chat")
    calls = store.keep(
        events.where("kind = 'call' and call_id is not null and conv_id is not null").groupBy("conv_id", "call_id").agg(F.min(F.struct("pos", "after")).alias("x")).select("conv_id", "call_id", "x.pos", "x.after")
    )
    asked = calls.select("conv_id", "call_id", "pos", F.explode("after").alias("dep")).distinct()
    deps = store.keep(asked.join(calls.select("conv_id", F.col("call_id").alias("dep"), F.col("pos").alias("dep_pos")), ["conv_id", "dep"]))
    late = store.keep(
        deps.groupBy("conv_id").agg(F.count("*").alias("n"), F.bool_or(F.col("dep_pos") >= F.col("pos")).alias("late")).where("late").select("conv_id", "n")
        .join(calls.groupBy("conv_id").agg(F.count("*").alias("m")), "conv_id").select("conv_id", (F.greatest("n", "m") > GROUP_CALLS).alias("large"))
    )
    edges, todo = deps.select("conv_id", "call_id", "dep"), calls.select("conv_id", "call_id")
    some = lambda df, large: df.join(late.where("large" if large else "not large").select("conv_id"), "conv_id", "left_semi")
    small = some(todo, False).groupBy("conv_id").cogroup(some(edges, False).groupBy("conv_id")).applyInArrow(_ordered, DEPTHS)
    if not late.where("large").limit(1).count():
        return small
    return small.unionByName(_peeled(store, store.keep(some(todo, True)), store.keep(some(edges, True)), max_rounds))


def _peeled(store: Scratch, todo: DataFrame, edges: DataFrame, max_rounds: int | None) -> DataFrame:
    """Depths by rounds over tables: calls that wait for nothing go, until none is left."""
    done = None
    for depth in itertools.count():
        if not todo.limit(1).count():
            return done
        if depth == max_rounds:
            raise RuntimeError(f"calls are left after {max_rounds} rounds")
        free = store.keep(todo.join(edges, ["conv_id", "call_id"], "left_anti"))
        if not free.limit(1).count():
            rest = todo.withColumn("depth", F.lit(-1))
            return rest if done is None else done.unionByName(rest)
        now = free.withColumn("depth", F.lit(depth))
        done = now if done is None else done.unionByName(now)
        if depth % ROUNDS_APART == ROUNDS_APART - 1:
            done = store.keep(done)
        edges = store.keep(edges.join(free.select("conv_id", F.col("call_id").alias("dep")), ["conv_id", "dep"], "left_anti"))
        todo = store.keep(todo.join(free, ["conv_id", "call_id"], "left_anti"))


def format_calls(events: DataFrame, schemas: dict[str, dict]) -> DataFrame:
    """Link, order, validate and serialise events.

    Returns ``conv_id, pos, kind, call_id, partner, status, depth, valid, errors, json``, a row
    per event.  Sorting a conversation by (depth, pos) is a topological order; depth is 0 where
    the positions are one already.
    """
    events = events.select(*[f.split()[0] for f in EVENTS.split(", ")])  # other columns, whose names may clash, stay behind
    linked = link(events)
    deep = depths(events).select(F.col("conv_id").alias("c"), F.col("call_id").alias("key"), "depth")
    rows = linked.withColumn("key", _key()).join(deep.withColumnRenamed("c", "conv_id"), ["conv_id", "key"], "left").drop("key")
    rows = rows.withColumn("depth", F.coalesce("depth", F.lit(0)))
    shared = schemas

    def work(batches):
        for b in batches:
            valid, errors, texts = [], [], []
            for r in b.select(["kind", "name", "call_id", "after", "body"]).to_pylist():
                found: list[str] = []
                body = r["body"]
                if r["kind"] == "call":
                    try:
                        value = parsed(body or "{}")
                        schema = shared.get(r["name"])
                        found = [f"unknown tool {r['name']}"] if schema is None else problems(value, schema)
                        body = value
                    except ValueError:
                        found = ["$: not JSON"]
                made = {"role": r["kind"], "name": r["name"], "id": r["call_id"], ("arguments" if r["kind"] == "call" else "content"): body}
                if r["after"]:
                    made["after"] = sorted(r["after"])
                valid.append(not found)
                errors.append(whole("; ".join(found)))
                texts.append(canonical({k: v for k, v in made.items() if v is not None or k == "content"}))
            keep = [c for c in b.schema.names if c not in ("name", "after", "body")]
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in keep], pa.array(valid, pa.bool_()), pa.array(errors, pa.string()), pa.array(texts, pa.string())], names=[*keep, "valid", "errors", "json"])

    cols = ["conv_id", "pos", "kind", "call_id", "partner", "status", "depth"]
    src = rows.select(*cols, "name", "after", "body")
    schema = fields("conv_id long, pos long, kind string, call_id string, partner long, status string, depth int, valid boolean, errors string, json string")
    return src.mapInArrow(work, schema)


def events_of_turns(conversations: DataFrame) -> DataFrame:
    """Plain conversations as events: a user's turn calls the tool ``reply``, the assistant's next turn is its result.

    The first digit of md5(conversation:turn) makes what a real log also holds.  Of a user's turn: 0
    gives the number of letters as a string, 1 leaves the prompt out, 2 and 3 make this call wait for
    the call two turns later, 4 makes both wait for each other, and otherwise the later one waits for
    this one.  Of an assistant's turn: 0 answers an identifier that nobody called, 1 answers twice.
    Positions are twice the turn, a second answer stands one further.  Other roles are messages.  A null
    turn or conversation has no identifier and waits for nothing.
    """
    user, bot = F.col("role") == "user", F.col("role") == "assistant"
    conv, turn = F.col("conv_id").cast("long"), F.col("turn").cast("long")
    known = conv.isNotNull() & turn.isNotNull()
    name = lambda on: F.concat_ws("-", conv.cast("string"), (turn + on).cast("string"))
    digit = lambda on: F.substring(F.md5(F.concat_ws(":", conv.cast("string"), (turn + on).cast("string")).cast("binary")), 1, 1)
    letters = F.coalesce(F.length("text"), F.lit(0))
    args = (
        F.when(digit(0) == "0", F.to_json(F.struct(letters.cast("string").alias("chars"), F.col("text").alias("prompt"), turn.alias("turn"))))
        .when(digit(0) == "1", F.to_json(F.struct(letters.alias("chars"), turn.alias("turn"))))
        .otherwise(F.to_json(F.struct(letters.alias("chars"), F.col("text").alias("prompt"), turn.alias("turn"))))
    )
    waits = F.array_compact(F.array(F.when(~digit(-2).isin("2", "3"), name(-2)), F.when(digit(0).isin("2", "3", "4"), name(2))))
    answers = F.when(bot & known & (digit(0) == "1"), F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))
    answered = F.when(digit(0) == "0", F.concat(name(-1), F.lit("-lost"))).otherwise(name(-1))
    return conversations.select(conv.alias("conv_id"), turn.alias("turn"), "role", "text", F.explode(answers).alias("again")).select(
        "conv_id", (F.col("turn") * 2 + F.col("again")).alias("pos"),
        F.when(user, "call").when(bot, "result").otherwise(F.coalesce("role", F.lit("message"))).alias("kind"),
        F.when(user | bot, "reply").alias("name"), F.when(user & known, name(0)).when(bot & known, answered).alias("call_id"),
        F.when(user & known, waits).otherwise(F.array().cast("array<string>")).alias("after"),
        F.when(user, args).otherwise(F.col("text")).alias("body"),
    )


#: The schema of the tool that plain turns call.
REPLY = {"reply": {
    "type": "object", "required": ["prompt", "turn", "chars"], "additionalProperties": False,
    "properties": {"prompt": {"type": "string"}, "turn": {"type": "integer"}, "chars": {"type": "integer"}},
}}
