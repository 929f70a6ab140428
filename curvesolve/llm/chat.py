"""Chat formatting with tool-call linking, in DataFrame expressions only.

A turn whose text is a JSON object may hold ``tool_calls`` [{id, name, arguments}], or the result of a
call: ``tool_call_id`` and ``content``. Other turns are plain text. Calls and results of a conversation
are linked by a hash join on the call's identifier; arguments may name other calls as {{id}}, and
calls are ordered topologically by these names; arguments are validated against the tool's schema;
each turn is serialised as canonical JSON (sorted keys, no blanks).

A linked result is placed right after its call: rows sort by (conv_id, at_turn, step, turn). No
conversation is gathered in one task.

Defined results: null roles become "user" and null texts ""; text that is no JSON object is plain
text; arguments that are no JSON object are invalid, and kept as a string if they are no JSON; a call's result is the first
one in a later turn; calls on a cycle of names keep step 0 and are marked; repeated rows are formatted
alike; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import cut, keyed_min

#: The type names of schemas, and how Spark names the type of a value.
TYPES = {"string": "^STRING$", "integer": "^BIGINT$", "number": "^(BIGINT|DOUBLE|FLOAT|DECIMAL.*)$", "boolean": "^BOOLEAN$",
         "array": "^ARRAY.*$", "object": "^OBJECT.*$"}
MESSAGE = "tool_calls array<struct<id string, name string, arguments string>>, tool_call_id string, content string"
#: A schema: {tool: {argument: (type, required)}}.
Schemas = dict[str, dict[str, tuple[str, bool]]]
#: The tools that the registered queries validate against.
TOOLS: Schemas = {"lookup": {"after": ("string", False), "words": ("integer", True)}, "search": {"limit": ("integer", False), "query": ("string", True)}}


def canonical(text: Column) -> Column:
    """Canonical JSON of a JSON text; null if it is none."""
    return F.to_json(F.try_parse_json(text))


def _quoted(text: Column) -> Column:
    """JSON text of a string."""
    listed = F.to_json(F.array(text))
    return F.substring(listed, F.lit(2), F.length(listed) - 2)


def problems(name: Column, arguments: Column, schemas: Schemas | None) -> Column:
    """array<string> of what is wrong with a call's arguments; empty: valid."""
    value = F.try_parse_json(arguments)
    is_object = F.coalesce(F.rlike(F.schema_of_variant(value), F.lit("^OBJECT")), F.lit(False))
    found = F.when(~is_object, F.array(F.lit("arguments:not an object")))
    for tool, args in (schemas or {}).items():
        checks = []
        for arg, (kind, required) in sorted(args.items()):
            kind_of = F.schema_of_variant(F.try_variant_get(value, f"$['{arg}']", "variant"))
            missing = F.lit(f"{arg}:missing") if required else F.lit(None).cast("string")
            checks.append(F.when(kind_of.isNull(), missing).when(~F.rlike(kind_of, F.lit(TYPES[kind])), F.lit(f"{arg}:not {kind}")))
        extra = F.transform(F.array_sort(F.array_except(F.json_object_keys(arguments), F.array(*[F.lit(a) for a in sorted(args)]).cast("array<string>"))),
                            lambda k: F.concat(k, F.lit(":unknown")))
        good = F.filter(F.array(*checks).cast("array<string>"), lambda x: x.isNotNull())
        found = found.when(name == tool, F.concat(good, F.coalesce(extra, F.array().cast("array<string>"))))
    rest = F.array(F.lit("name:unknown tool")) if schemas else F.array().cast("array<string>")
    return found.otherwise(rest)


def parse(turns: DataFrame) -> DataFrame:
    """(rid, conv_id, turn, role, text, m): rid identifies a row's content, m is the parsed message or null."""
    src = turns.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"),
                       F.coalesce(F.col("role").cast("string"), F.lit("user")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    parsed = F.when(F.rlike("text", F.lit(r"^\s*\{")), F.from_json("text", MESSAGE))
    parsed = F.when(parsed["tool_calls"].isNotNull() | parsed["tool_call_id"].isNotNull(), parsed)
    return src.select(F.xxhash64("conv_id", "turn", "role", "text").alias("rid"), "*", parsed.alias("m"))


def tool_calls(messages: DataFrame, schemas: Schemas | None = None) -> DataFrame:
    """One row per call: rid, conv_id, turn, idx, id, name, arguments (canonical), problems, depends on, result_turn."""
    calls = messages.where("m.tool_calls is not null").select("rid", "conv_id", "turn", F.posexplode("m.tool_calls").alias("idx", "c")).distinct()
    calls = calls.select("rid", "conv_id", "turn", "idx", "c.id", "c.name", F.coalesce(canonical(F.col("c.arguments")), _quoted(F.coalesce("c.arguments", F.lit("")))).alias("arguments"),
                         problems(F.col("c.name"), F.col("c.arguments"), schemas).alias("problems"),
                         F.array_distinct(F.regexp_extract_all(F.coalesce("c.arguments", F.lit("")), F.lit(r"\{\{([A-Za-z0-9_.-]+)\}\}"), F.lit(1))).alias("needs"))
    results = messages.where("m.tool_call_id is not null").select(F.col("conv_id").alias("_conv"), F.col("turn").alias("_turn"), F.col("m.tool_call_id").alias("_id")).distinct()
    met = calls.select("rid", "idx", "conv_id", "turn", "id").join(results.hint("shuffle_hash"), (F.col("conv_id") == F.col("_conv")) & (F.col("id") == F.col("_id")) & (F.col("_turn") > F.col("turn")))
    first = met.groupBy("rid", "idx").agg(F.min("_turn").alias("result_turn"))
    return calls.join(first, ["rid", "idx"], "left")


def topological(calls: DataFrame) -> DataFrame:
    """(conv_id, id, step): 0 for calls that need no other, else one more than the latest needed; null on a cycle.

    One round per step; a round drops the calls whose needs are all placed.
    """
    nodes = cut(calls.where("id is not null").select("conv_id", "id").distinct())
    edges = calls.select("conv_id", "id", F.explode("needs").alias("need")).distinct()
    edges = cut(edges.join(nodes.withColumnRenamed("id", "need"), ["conv_id", "need"]).where("id is not null"))
    placed, step = [], 0
    while not edges.isEmpty():
        ready = cut(nodes.join(edges, ["conv_id", "id"], "left_anti"))
        if ready.isEmpty():
            break
        placed.append(ready.withColumn("step", F.lit(step)))
        nodes = cut(nodes.join(ready, ["conv_id", "id"], "left_anti"))
        edges = cut(edges.join(ready.withColumnRenamed("id", "need"), ["conv_id", "need"], "left_anti"))
        step += 1
    out = nodes.withColumn("step", F.lit(step) if edges.isEmpty() else F.lit(None).cast("int"))
    for p in placed:
        out = out.unionByName(p)
    return out


def format_turns(turns: DataFrame, schemas: Schemas | None = None) -> DataFrame:
    """One row per turn: conv_id, turn, role, at_turn, step, n_calls, n_linked, n_invalid, n_cyclic, json."""
    messages = parse(turns)
    calls = cut(tool_calls(messages, schemas))
    order = topological(calls)
    placed = calls.join(order, ["conv_id", "id"], "left")
    cyclic = F.col("step").isNull() & F.col("id").isNotNull()
    per_turn = placed.groupBy(F.col("rid").alias("_rid")).agg(
        F.array_sort(F.collect_list(F.struct(F.coalesce("step", F.lit(0)).alias("step"), "idx", "arguments", "id", "name", F.when(F.size("problems") > 0, F.col("problems")).alias("problems")))).alias("calls"),
        F.count("result_turn").alias("n_linked"), F.count_if(F.size("problems") > 0).alias("n_invalid"), F.count_if(cyclic).alias("n_cyclic"))
    # Where a linked result goes: after its call, by the call's turn, step and number.
    target = placed.where("result_turn is not null").select(
        F.xxhash64("conv_id", "id", "result_turn").alias("k"), F.struct(F.col("turn").alias("at"), (1 + F.coalesce("step", F.lit(0))).alias("step")).alias("to"))
    target = keyed_min(target, "k", "to", "to")
    both = messages.withColumn("k", F.xxhash64("conv_id", "m.tool_call_id", "turn")).withColumn("is_result", F.col("m.tool_call_id").isNotNull())
    both = both.join(per_turn, F.col("rid") == F.col("_rid"), "left").join(
        target.withColumnRenamed("k", "_k"), F.col("is_result") & (F.col("k") == F.col("_k")), "left")
    content = F.when(F.col("m").isNull(), F.col("text")).otherwise(F.coalesce("m.content", F.lit("")))
    json = F.to_json(F.struct(content.alias("content"), F.col("role"), F.col("m.tool_call_id").alias("tool_call_id"),
                              F.transform("calls", lambda c: F.struct(F.try_parse_json(c["arguments"]).alias("arguments"), c["id"].alias("id"), c["name"].alias("name"), c["problems"].alias("problems"))).alias("tool_calls")))
    zero = F.lit(0).cast("long")
    return both.select(
        "conv_id", "turn", "role", F.coalesce("to.at", "turn").alias("at_turn"), F.coalesce("to.step", F.lit(0)).alias("step"),
        F.greatest(F.coalesce(F.size("calls"), F.lit(0)), F.lit(0)).cast("long").alias("n_calls"), F.coalesce("n_linked", zero).alias("n_linked"),
        F.coalesce("n_invalid", zero).alias("n_invalid"), F.coalesce("n_cyclic", zero).alias("n_cyclic"), json.alias("json"))


def as_tool_calls(turns: DataFrame) -> DataFrame:
    """Conversations in which every odd turn is a call of ``lookup`` that needs the one two turns before, and every even
    turn but the first the result of the call before it; a third of the conversations give a word count as text."""
    words = F.size(F.split(F.col("text"), " ", -1))
    arguments = F.struct(F.when(F.col("turn") > 1, F.concat(F.lit("{{c"), (F.col("turn") - 2).cast("string"), F.lit("}}"))).alias("after"),
                         F.when(F.col("conv_id") % 3 == 0, F.try_parse_json(F.concat(F.lit('"'), words.cast("string"), F.lit('"')))).otherwise(F.try_parse_json(words.cast("string"))).alias("words"))
    call = F.struct(F.array(F.struct(F.concat(F.lit("c"), F.col("turn").cast("string")).alias("id"), F.lit("lookup").alias("name"), arguments.alias("arguments"))).alias("tool_calls"))
    result = F.struct(F.concat(F.lit("c"), (F.col("turn") - 1).cast("string")).alias("tool_call_id"), F.col("text").alias("content"))
    text = F.when(F.col("turn") % 2 == 1, F.to_json(call)).when(F.col("turn") > 0, F.to_json(result)).otherwise(F.col("text"))
    return turns.select("conv_id", "turn", "role", text.alias("text"))
