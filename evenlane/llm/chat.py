"""Tool-call linking with built-in functions only: calls and results meet by identifier.

Every event gives one row with its status, its place in a topological order and canonical JSON (keys in
order, no white space). Nothing gathers a conversation in one place, so one conversation may hold any share of the rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenlane.staging import discard, stage


#: Tool -> argument -> (type, required); types: string, integer, number, boolean, array, object.
Schemas = dict[str, dict[str, tuple[str, bool]]]
REPLY: Schemas = {"reply": {"breaks": ("integer", True), "text": ("string", True), "turn": ("integer", True)}}
_TYPES = {"string": "^STRING$", "integer": "^BIGINT$", "number": "^(BIGINT|DOUBLE|FLOAT|DECIMAL)", "boolean": "^BOOLEAN$", "array": "^ARRAY<", "object": "^OBJECT<"}


def arguments_fit(v: Column, name: Column, schemas: Schemas) -> Column:
    """Whether the arguments (a variant) are an object with the tool's required arguments, right types, and no others."""
    fit = F.lit(False)
    for tool, args in schemas.items():
        checks = F.schema_of_variant(v).startswith("OBJECT<")
        for a, (kind, required) in args.items():
            found = F.schema_of_variant(F.try_variant_get(v, f"$['{a}']", "variant"))
            checks &= F.coalesce(found.rlike(_TYPES[kind]), F.lit(not required))
        extra = F.array_except(F.coalesce(F.json_object_keys(v.cast("string")), F.array().cast("array<string>")), F.array(*map(F.lit, args)).cast("array<string>"))
        fit = F.when(name == tool, checks & (F.size(extra) == 0)).otherwise(fit)
    return F.coalesce(fit, F.lit(False))


def depths(calls: DataFrame) -> DataFrame:
    """Rows (call_id, depth) of calls (call_id, after): 0 without needs, else one more than the deepest need.

    Needs that name no call are void. Calls in or behind a cycle are absent. Calls with a single need form
    chains, which pointer doubling follows to their heads, in as many rounds as a chain's length has bits; what is left are calls
    with several needs, one round a level of these.
    """
    nodes = stage(calls.where("call_id is not null").groupBy("call_id").agg(F.flatten(F.collect_set("after")).alias("after")), "chat-calls")
    edges = nodes.select("call_id", F.explode(F.array_distinct("after")).alias("need"))
    edges = stage(edges.join(nodes.select(F.col("call_id").alias("need")), "need"), "chat-edges")
    free = nodes.join(edges, "call_id", "left_anti").select("call_id", F.lit(0).alias("depth"))
    if edges.isEmpty():
        return free
    needs = edges.groupBy("call_id").agg(F.count("*").alias("n"), F.first("need").alias("head"))
    chained = stage(needs.where("n = 1").select("call_id", "head", F.lit(1).alias("steps")), "chat-chains")
    rounds = max(1, chained.count()).bit_length() + 1
    for _ in range(rounds):  # a chain still open after these is a cycle
        further = chained.select(F.col("call_id").alias("head"), F.col("head").alias("next"), F.col("steps").alias("more"))
        nxt = stage(chained.join(further, "head", "left").select("call_id", F.coalesce("next", "head").alias("head"), (F.col("steps") + F.coalesce("more", F.lit(0))).alias("steps")), "chat-chains")
        still = nxt.join(nxt.select(F.col("call_id").alias("head")), "head", "left_semi")
        discard(chained)
        chained = nxt
        if still.isEmpty():
            break
    chained = chained.join(chained.select(F.col("call_id").alias("head")), "head", "left_anti")
    several = edges.join(needs.where("n > 1").select("call_id"), "call_id", "left_semi")
    links = several.join(chained.withColumnRenamed("call_id", "need"), "need", "left").join(needs.where("n = 1").select(F.col("call_id").alias("need"), F.lit(True).alias("single")), "need", "left")
    # a need in a cycle of single needs has no head: its link keeps a head that never gets a depth
    links = stage(links.select("call_id", F.when(F.col("head").isNotNull(), F.col("head")).when(F.col("single"), F.lit(None)).otherwise(F.col("need")).alias("head"), (F.coalesce("steps", F.lit(0)) + 1).alias("steps")), "chat-links")
    done = levels = stage(free, "chat-depths")
    while not links.isEmpty():
        open_ = links.join(done.withColumnRenamed("call_id", "head"), "head", "left")
        ready = open_.groupBy("call_id").agg(F.max(F.col("depth") + F.col("steps")).alias("d"), F.count_if(F.col("depth").isNull()).alias("missing")).where("missing = 0")
        level = stage(ready.select("call_id", F.col("d").cast("int").alias("depth")), "chat-level")
        if level.isEmpty():
            break
        old, links = links, stage(links.join(level, "call_id", "left_anti"), "chat-links")
        discard(old)
        done = done.union(level)
        levels = done
    heads = levels.withColumnRenamed("call_id", "head")
    return levels.union(chained.join(heads, "head").select("call_id", (F.col("depth") + F.col("steps")).cast("int").alias("depth")))


def link_tool_calls(events: DataFrame, schemas: Schemas) -> DataFrame:
    """Rows (conv_id, turn, kind, call_id, level, status, json), one for each event.

    events: conv_id, turn, kind (call, result or message), call_id, name, arguments (JSON text), content,
    role, after (array of call_ids whose results a call needs). level orders each conversation: twice the
    call's depth, one more for its results, then by turn. Statuses: ok; no_id (null identifier); duplicate_id
    (an earlier call has it; ties by name and arguments, equal rows all count as first); unknown_tool; bad_arguments; cycle; no_result; orphan.
    Null fields are JSON null; arguments that are no JSON become null and are bad; an empty table gives an empty result.
    Other columns are ignored, whatever their names.
    """
    e = events.select("conv_id", "turn", "kind", "call_id", "name", "arguments", "content", "role", "after").withColumn("v", F.try_parse_json("arguments"))
    mine = F.when(F.col("kind") == "call", F.struct("turn", "conv_id", "name", "arguments"))
    ids = e.where("call_id is not null and kind in ('call', 'result')").groupBy("call_id").agg(
        F.min(mine).alias("first"), F.count_if(F.col("kind") == "call").alias("calls"), F.count_if(F.col("kind") == "result").alias("results")
    )
    depth = depths(e.where("kind = 'call'").select("call_id", "after"))
    ids = stage(ids.join(depth, "call_id", "left"), "chat-ids")
    # events without an identifier match nothing: a key of their own spreads them over the partitions
    alone = F.xxhash64("conv_id", "turn", "content").cast("string")
    keyed = e.withColumns({"key": F.coalesce("call_id", alone), "named": F.col("call_id").isNotNull()})
    j = keyed.join(ids.withColumnRenamed("call_id", "key").withColumn("named", F.lit(True)), ["key", "named"], "left")
    call, result = F.col("kind") == "call", F.col("kind") == "result"
    status = (
        F.when(~call & ~result, "ok")
        .when(F.col("call_id").isNull(), "no_id")
        .when(result, F.when(F.col("calls") > 0, "ok").otherwise("orphan"))
        .when(~F.struct("turn", "conv_id", "name", "arguments").eqNullSafe(F.col("first")), "duplicate_id")
        .when(~F.coalesce(F.col("name").isin(*schemas), F.lit(False)), "unknown_tool")
        .when(~arguments_fit(F.col("v"), F.col("name"), schemas), "bad_arguments")
        .when(F.col("depth").isNull(), "cycle")
        .when(F.col("results") == 0, "no_result")
        .otherwise("ok")
    )
    level = F.when(call, 2 * F.col("depth")).when(result, 2 * F.col("depth") + 1).otherwise(0).cast("long")
    tail = lambda *names: F.substring(F.to_json(F.struct(*[c.alias(n) for n, c in names]), {"ignoreNullFields": "false"}), 2, 2**31 - 1)
    json = (
        F.when(call, F.concat(F.lit('{"arguments":'), F.coalesce(F.col("v").cast("string"), F.lit("null")), F.lit(","), tail(("id", F.col("call_id")), ("name", F.col("name")), ("type", F.lit("call")))))
        .when(result, F.concat(F.lit("{"), tail(("content", F.col("content")), ("id", F.col("call_id")), ("type", F.lit("result")))))
        .otherwise(F.concat(F.lit("{"), tail(("content", F.col("content")), ("role", F.col("role")), ("type", F.lit("message")))))
    )
    return j.select("conv_id", "turn", "kind", "call_id", level.alias("level"), status.alias("status"), json.alias("json"))


def turns_as_events(conversations: DataFrame) -> DataFrame:
    """Events of plain conversations: a user's turn calls the tool `reply`, the next turn of the assistant is its result.

    A call needs the result of the user's turn before it, two turns back. Its arguments are the text, the turn and
    the number of line breaks, which is null in a text of one line, and then not what the tool's schema asks for.
    """
    c = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")
    name = lambda t: F.concat(F.col("conv_id").cast("string"), F.lit("-"), t.cast("string"))
    user, bot = F.col("role") == "user", F.col("role") == "assistant"
    breaks = F.length("text") - F.length(F.replace("text", F.lit("\n")))
    arguments = F.struct(F.when(breaks > 0, breaks).alias("breaks"), "text", "turn")
    return c.select(
        "conv_id", "turn", F.when(user, "call").when(bot, "result").otherwise("message").alias("kind"),
        F.when(user, name(F.col("turn"))).when(bot, name(F.col("turn") - 1)).alias("call_id"), F.when(user, "reply").alias("name"),
        F.when(user, F.to_json(arguments, {"ignoreNullFields": "false"})).alias("arguments"), F.when(~user | user.isNull(), F.col("text")).alias("content"), "role",
        F.when(user, F.array(name(F.col("turn") - 2))).otherwise(F.array().cast("array<string>")).alias("after"),
    )


def chat_query(spark, sf_dir: str) -> DataFrame:
    return link_tool_calls(turns_as_events(spark.read.parquet(f"{sf_dir}/conversations.parquet")), REPLY)


CHAT_SQL = """
WITH t AS (SELECT *, nullif(length(text) - length(replace(text, chr(10), '')), 0) AS breaks FROM conversations),
e AS (SELECT conv_id, turn, role, text, breaks, CASE role WHEN 'user' THEN 'call' WHEN 'assistant' THEN 'result' ELSE 'message' END AS kind,
  CASE role WHEN 'user' THEN conv_id || '-' || turn WHEN 'assistant' THEN conv_id || '-' || (turn - 1) END AS call_id,
  CASE role WHEN 'user' THEN CAST(json_object('breaks', breaks, 'text', text, 'turn', turn) AS VARCHAR) END AS args FROM t),
u AS (SELECT DISTINCT conv_id, turn, call_id FROM e WHERE kind = 'call' AND call_id IS NOT NULL),
g AS (SELECT *, turn - 2 * row_number() OVER (PARTITION BY conv_id, turn % 2 ORDER BY turn) AS island FROM u),
dep AS (SELECT call_id, row_number() OVER (PARTITION BY conv_id, turn % 2, island ORDER BY turn) - 1 AS depth FROM g),
i AS (SELECT call_id, count(*) FILTER (kind = 'call') AS calls, count(*) FILTER (kind = 'result') AS results,
  min(args) FILTER (kind = 'call') AS head FROM e WHERE call_id IS NOT NULL GROUP BY call_id)
SELECT conv_id, turn, kind, e.call_id, CAST(CASE kind WHEN 'result' THEN 2 * depth + 1 WHEN 'call' THEN 2 * depth ELSE 0 END AS BIGINT) AS level,
  CASE WHEN kind = 'message' THEN 'ok' WHEN e.call_id IS NULL THEN 'no_id' WHEN kind = 'result' THEN CASE WHEN calls > 0 THEN 'ok' ELSE 'orphan' END
    WHEN args <> head THEN 'duplicate_id' WHEN text IS NULL OR breaks IS NULL THEN 'bad_arguments' WHEN results = 0 THEN 'no_result' ELSE 'ok' END AS status,
  CASE kind WHEN 'call' THEN '{"arguments":' || args || ',' || substr(CAST(json_object('id', e.call_id, 'name', 'reply', 'type', 'call') AS VARCHAR), 2)
    WHEN 'result' THEN CAST(json_object('content', text, 'id', e.call_id, 'type', 'result') AS VARCHAR)
    ELSE CAST(json_object('content', text, 'role', role, 'type', 'message') AS VARCHAR) END AS json
FROM e LEFT JOIN i USING (call_id) LEFT JOIN dep USING (call_id)
"""
