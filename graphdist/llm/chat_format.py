"""Chat formatting with tool-call linking.

A message may carry tool calls: its text is a JSON object ``{"content"?, "tool_calls": [{"id", "name", "arguments"}]}``; a
message of role ``tool``, or with a text ``{"tool_call_id", "content"}``, carries the result of a call. Everything else is
plain text. Calls and results meet in a hash join on (conversation, call id).

Order: a result comes after its call, and a message after the results its arguments name (``"$ref:ID"``); otherwise turns
stand in their order. Each message gets the key (latest turn it must follow, depth) by peeling the reference graph: what waits
for nothing is settled first. A component of that graph (not a conversation) of up to ``LOCAL`` references is peeled in one task; larger ones
are peeled by rounds of joins, as many as they are deep. Messages on a cycle keep their turn and are marked; what only follows a cycle is
ordered after it and not marked (in components peeled by joins, messages between two cycles are marked, too).

Arguments are checked against the schema of their tool (object types, required, properties, enum). Every message is
written as canonical JSON: sorted keys, no blanks, UTF-8.

Defined cases: the text NULL is content null; text that is no such JSON object is plain content; a repeated call id keeps
the first call (smallest turn) as the link and n_repeated counts the calls of a message that are not the first of their id; a result without call is an orphan; repeated rows stay; a
NULL conv_id is a conversation of its own; empty tables give empty tables; other columns are dropped.
"""

from __future__ import annotations

import json

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F, types as T

from graphdist.llm.arrow_io import slices, tidy
from graphdist.operators.components import connected_components
from graphdist.runtime import discard, materialize

LOCAL, SLICE = 100_000, 8 << 20
#: Tools known to the production query: argument schemas by name.
TOOLS = {
    "search": {"type": "object", "required": ["query"], "properties": {"query": {"type": "string"}, "limit": {"type": "integer"}}},
    "calculator": {"type": "object", "required": ["expression"], "properties": {"expression": {"type": "string"}}},
}
_KINDS = {"string": str, "number": (int, float), "integer": int, "boolean": bool, "array": list, "object": dict, "null": type(None)}


def canonical(value) -> str:
    return json.dumps(value, sort_keys=True, separators=(",", ":"), ensure_ascii=False)


def conforms(value, schema: dict) -> bool:
    """Whether a value fits the supported part of JSON Schema."""
    kind = schema.get("type")
    if kind:
        kinds = kind if isinstance(kind, list) else [kind]
        if not any(isinstance(value, _KINDS[k]) and not (isinstance(value, bool) and k in ("integer", "number")) for k in kinds):
            return False
    if "enum" in schema and value not in schema["enum"]:
        return False
    if isinstance(value, dict):
        props = schema.get("properties", {})
        if any(k not in value for k in schema.get("required", ())):
            return False
        if schema.get("additionalProperties") is False and any(k not in props for k in value):
            return False
        return all(conforms(v, props[k]) for k, v in value.items() if k in props)
    if isinstance(value, list) and "items" in schema:
        return all(conforms(v, schema["items"]) for v in value)
    return True


def _refs(value) -> list[str]:
    if isinstance(value, str):
        return [value[5:]] if value.startswith("$ref:") else []
    if isinstance(value, dict):
        return [r for v in value.values() for r in _refs(v)]
    if isinstance(value, list):
        return [r for v in value for r in _refs(v)]
    return []


def read_message(role, text, tools: dict) -> dict:
    """The message as canonical JSON with the calls it makes, the call it answers and the results it needs."""
    out = {"calls": [], "answers": None, "needs": [], "n_invalid": 0}
    value = None
    if text and text.lstrip()[:1] == "{":
        try:
            value = json.loads(text)
        except (ValueError, RecursionError):
            value = None
    body = {"role": role, "content": text}
    if isinstance(value, dict) and isinstance(value.get("tool_calls"), list) and all(isinstance(c, dict) and isinstance(c.get("id"), str) for c in value["tool_calls"]):
        calls = []
        for c in value["tool_calls"]:
            args = c.get("arguments", {})
            if isinstance(args, str):
                try:
                    args = json.loads(args)
                except (ValueError, RecursionError):
                    pass
            schema = tools.get(c.get("name"))
            valid = schema is not None and conforms(args, schema)
            out["n_invalid"] += not valid
            calls.append({"id": c["id"], "name": c.get("name"), "arguments": args, "valid": valid})
            out["calls"].append(c["id"])
            out["needs"] += _refs(args)
        body = {"role": role, "content": value.get("content"), "tool_calls": calls}
    elif isinstance(value, dict) and isinstance(value.get("tool_call_id"), str):
        body = {"role": role, "content": value.get("content"), "tool_call_id": value["tool_call_id"]}
        out["answers"] = value["tool_call_id"]
    out["json"] = canonical(body)
    return out


_READ = T.StructType([
    T.StructField("conv_id", T.LongType()), T.StructField("turn", T.LongType()), T.StructField("role", T.StringType()), T.StructField("json", T.StringType()),
    T.StructField("calls", T.ArrayType(T.StringType())), T.StructField("answers", T.StringType()), T.StructField("needs", T.ArrayType(T.StringType())),
    T.StructField("n_invalid", T.IntegerType()),
])


def read_messages(messages: DataFrame, tools: dict = TOOLS) -> DataFrame:
    @tidy
    def run(batches):
        for b in (part for whole in batches for part in slices(whole, "text", SLICE)):
            found = [read_message(r, t, tools) for r, t in zip(b.column(2).to_pylist(), b.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0), b.column(1), b.column(2), pa.array([f["json"] for f in found], pa.string()), pa.array([f["calls"] for f in found], pa.list_(pa.string())),
                    pa.array([f["answers"] for f in found], pa.string()), pa.array([f["needs"] for f in found], pa.list_(pa.string())), pa.array([f["n_invalid"] for f in found], pa.int32()),
                ],
                [f.name for f in _READ.fields],
            )

    slim = messages.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    return slim.mapInArrow(run, _READ)


def format_chats(messages: DataFrame, tools: dict = TOOLS) -> DataFrame:
    """One row a message: conv_id, position (from 0 in its conversation), turn, role, json, n_calls, n_invalid, n_repeated, linked, orphan, cyclic."""
    read = read_messages(messages, tools).withColumn("mid", F.xxhash64("conv_id", "turn", "role", "json"))
    read = materialize(read, "chat")
    calls = read.select("conv_id", "turn", "mid", F.explode("calls").alias("call"))
    first = calls.groupBy("conv_id", "call").agg(F.min(F.struct("turn", "mid")).alias("c")).select("conv_id", "call", F.col("c.mid").alias("from_mid"))
    results = read.filter("answers is not null").select("conv_id", F.col("answers").alias("call"), "mid", "turn")
    match = lambda a, b: a["conv_id"].eqNullSafe(b["conv_id"]) & (a["call"] == b["call"])
    linked = results.join(first.hint("shuffle_hash"), match(results, first), "left").select(results["mid"].alias("mid"), "from_mid").distinct()
    needs = read.select("conv_id", "mid", F.explode("needs").alias("call"))
    answered = results.groupBy("conv_id", "call").agg(F.min(F.struct("turn", "mid")).alias("r")).select("conv_id", "call", F.col("r.mid").alias("from_mid"))
    wanted = needs.join(answered.hint("shuffle_hash"), match(needs, answered)).select(needs["mid"].alias("mid"), "from_mid")
    after = materialize(linked.filter("from_mid is not null").union(wanted).distinct(), "chat-after")
    named = first.select(F.col("conv_id").alias("conv"), F.col("call").alias("id"), "from_mid")
    other = calls.join(named.hint("shuffle_hash"), F.col("conv_id").eqNullSafe(F.col("conv")) & (F.col("call") == F.col("id"))).filter("mid != from_mid")
    repeats = other.groupBy("mid").agg(F.count_distinct("call").alias("n_repeated"))
    keys = _order(read, after)
    out = read.join(linked.withColumn("has_link", F.lit(True)), "mid", "left").join(keys, "mid", "left").join(repeats, "mid", "left")
    out = out.withColumn("cyclic", F.coalesce("cyclic", F.lit(False)))
    w = Window.partitionBy("conv_id").orderBy(F.coalesce("late", "turn").asc_nulls_last(), F.coalesce("depth", F.lit(0)), "turn", "mid")
    return out.select(
        "conv_id", (F.row_number().over(w) - 1).cast("long").alias("position"), "turn", "role", "json", F.size("calls").cast("long").alias("n_calls"),
        F.col("n_invalid").cast("long").alias("n_invalid"), F.coalesce("n_repeated", F.lit(0)).cast("long").alias("n_repeated"), F.col("from_mid").isNotNull().alias("linked"),
        (F.col("answers").isNotNull() & F.col("from_mid").isNull()).alias("orphan"), "cyclic",
    )


def order_messages(turns: dict, before: list[tuple]) -> dict:
    """mid -> (late, depth, cyclic) for messages with their turns (None sorts last), given (mid, mid it must follow) pairs."""
    big = max((t for t in turns.values() if t is not None), default=0) + 1
    own = {m: big if t is None else t for m, t in turns.items()}
    into: dict = {m: set() for m in own}
    out: dict = {m: set() for m in own}
    for m, f in before:
        into[m].add(f)
        out[f].add(m)
    found = {}
    for group in _strong(own, out):
        ring = len(group) > 1 or group[0] in out[group[0]]
        for m in group:  # groups come with all they follow before them
            if ring:
                found[m] = (own[m], 0, True)
            else:
                found[m] = max([(own[m], 0), *((found[f][0], found[f][1] + 1) for f in into[m])]) + (False,)
    return {m: (None if late == big else late, depth, ring) for m, (late, depth, ring) in found.items()}


def _strong(nodes, out) -> list[list]:
    """Strongly connected groups in topological order, without recursion."""
    index, low, on, stack, groups = {}, {}, set(), [], []
    for root in sorted(nodes):
        if root in index:
            continue
        work = [(root, iter(sorted(out[root])))]
        index[root] = low[root] = len(index)
        stack.append(root)
        on.add(root)
        while work:
            v, rest = work[-1]
            for w in rest:
                if w not in index:
                    index[w] = low[w] = len(index)
                    stack.append(w)
                    on.add(w)
                    work.append((w, iter(sorted(out[w]))))
                    break
                if w in on:
                    low[v] = min(low[v], index[w])
            else:
                work.pop()
                if work:
                    low[work[-1][0]] = min(low[work[-1][0]], low[v])
                if low[v] == index[v]:
                    group = []
                    while True:
                        w = stack.pop()
                        on.discard(w)
                        group.append(w)
                        if w == v:
                            break
                    groups.append(group)
    return groups[::-1]


def _local(frame: pd.DataFrame) -> pd.DataFrame:
    turns = {}
    for ids, ts in (("mid", "turn"), ("from_mid", "from_turn")):
        turns.update({int(m): None if pd.isna(t) else int(t) for m, t in zip(frame[ids], frame[ts])})
    found = order_messages(turns, list(zip(frame["mid"].tolist(), frame["from_mid"].tolist())))
    return pd.DataFrame([(m, *v) for m, v in found.items()], columns=["mid", "late", "depth", "cyclic"]).astype({"late": "Int64"})


def _order(read: DataFrame, after: DataFrame, local: int = LOCAL) -> DataFrame:
    """(mid, late, depth, cyclic) for messages that must follow others or are followed."""
    turns = read.select("mid", "turn").distinct()
    comp = connected_components(after.select(F.col("mid").alias("a"), F.col("from_mid").alias("b")))
    named = after.join(comp, after["mid"] == comp["id"], "left").select("mid", "from_mid", F.coalesce("component", "mid").alias("c"))
    sizes = named.groupBy("c").agg((F.count("*") > local).alias("large"))
    full = named.join(turns, "mid").join(turns.select(F.col("mid").alias("from_mid"), F.col("turn").alias("from_turn")), "from_mid").join(sizes, "c")
    full = materialize(full, "chat-order")
    small = full.filter("not large").groupBy("c").applyInPandas(_local, "mid long, late long, depth int, cyclic boolean")
    return small.union(_peel(full.filter("large").select("mid", "from_mid", "turn", "from_turn")))


def _peel(edges: DataFrame) -> DataFrame:
    """The same for components too large for one task, by rounds of joins."""
    ends = edges.select("mid", "turn").union(edges.select("from_mid", "from_turn")).groupBy("mid").agg(F.min("turn").alias("late"))
    top = 2**62
    state = materialize(ends.select("mid", F.coalesce("late", F.lit(top)).alias("own"), F.struct(F.coalesce("late", F.lit(top)).alias("late"), F.lit(0).alias("depth")).alias("key")), "chat-order")
    left = materialize(edges.select("mid", "from_mid"), "chat-order")
    done = state.limit(0)
    while not state.isEmpty():
        ready = materialize(state.join(left.select("mid").distinct(), "mid", "left_anti"), "chat-order")
        if ready.isEmpty():
            break
        raised = left.join(ready.select(F.col("mid").alias("from_mid"), "key"), "from_mid").groupBy("mid").agg(F.max(F.struct("key.late", (F.col("key.depth") + 1).alias("depth"))).alias("r"))
        rest = state.join(ready.select("mid"), "mid", "left_anti").join(raised, "mid", "left")
        new_state = materialize(rest.select("mid", "own", F.greatest("key", F.coalesce("r", "key")).alias("key")), "chat-order")
        new_left = materialize(left.join(ready.select(F.col("mid").alias("from_mid")), "from_mid", "left_anti").select("mid", "from_mid"), "chat-order")
        discard(state, left)
        state, left, done = new_state, new_left, done.union(ready)
    while not state.isEmpty():  # what nothing waits for is no part of a cycle
        inner = left.select(F.col("from_mid").alias("mid")).distinct()
        free = materialize(state.join(inner, "mid", "left_anti"), "chat-order")
        if free.isEmpty():
            break
        done = done.union(free.withColumn("key", F.struct(F.greatest("own", "key.late").alias("late"), (F.col("key.depth") + 1).alias("depth"))))
        new_state = materialize(state.join(free.select("mid"), "mid", "left_anti"), "chat-order")
        new_left = materialize(left.join(free.select("mid"), "mid", "left_anti"), "chat-order")
        state, left = new_state, new_left
    settled = done.select("mid", F.nullif("key.late", F.lit(top)).alias("late"), F.col("key.depth").cast("int").alias("depth"), F.lit(False).alias("cyclic"))
    return settled.union(state.select("mid", F.nullif("own", F.lit(top)).alias("late"), F.lit(0).alias("depth"), F.lit(True).alias("cyclic")))


def op4_chat_format(spark, sf_dir):
    return format_chats(spark.read.parquet(f"{sf_dir}/conversations.parquet")).select(
        "conv_id", "position", "turn", "role", "json", "n_calls", "n_invalid", "linked", "orphan", "cyclic"
    )


# The tables hold plain messages only, so the linking parts are constants here; fixtures in the tests cover them.
OP4_SQL = """
SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, text) - 1 AS position, turn, role,
  '{"content":' || coalesce(CAST(to_json(text) AS VARCHAR), 'null') || ',"role":' || coalesce(CAST(to_json(role) AS VARCHAR), 'null') || '}' AS json,
  CAST(0 AS BIGINT) AS n_calls, CAST(0 AS BIGINT) AS n_invalid, false AS linked, false AS orphan, false AS cyclic
FROM conversations
"""
