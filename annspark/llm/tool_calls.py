"""Tool-call linking: calls and results meet by identifier, are ordered by dependency, checked and written as canonical JSON.

Only DataFrame and SQL functions. Messages are rows (conv_id, turn, role, text). A call message (role ``assistant``) is JSON with
``tool_calls``, an array of {id, name, arguments, depends_on}; a result message (role ``tool``) is JSON with ``tool_call_id`` and ``content``.
Calls and results are hash-joined by (conv_id, id). A call's level is the longest chain of
calls of its conversation that it depends on; levels are found in rounds that halve chains, on tables keyed by (conv_id, id), so no
conversation is ever gathered in one place. Sorting by (level, turn, id) is a topological order; calls on or behind
a cycle have a null level. Dependencies on identifiers that no call has are ignored and listed as ``dangling``.
Arguments are checked against the tool's schema: ``malformed`` (no JSON object), ``unknown-tool``, ``missing:field``, ``type:field``, ``extra:field``.
Canonical JSON has sorted keys, no spaces and no null fields.

Edge cases: text that is null, empty or no such JSON gives no call and no result; of calls that repeat an
identifier in a conversation the first by (turn, name, arguments) counts; of several results the first by (turn, content) is linked
and ``n_results`` counts them all; results whose identifier no call of the conversation has are left out, as in ``SQL``; null conv_ids belong together; a null identifier or a null turn is dropped from linking as no identifier can be given; an empty
table gives no rows; a very long text is parsed whole; further columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD, cut, forget, table

CALLS = "STRUCT<tool_calls: ARRAY<STRUCT<id: STRING, name: STRING, arguments: STRING, depends_on: ARRAY<STRING>>>>"
RESULT = "STRUCT<tool_call_id: STRING, content: STRING>"
#: The schemas that the turns of a plain conversation are checked against: field -> (type, required).
TURN_TOOLS = {
    "configure": {"instructions": ("string", True)},
    "reply": {"prompt": ("string", True), "turn": ("integer", True), "words": ("integer", False)},
}
_TYPES = {"string": "^STRING$", "integer": "^BIGINT$", "number": "^(BIGINT|DOUBLE|FLOAT|DECIMAL.*)$", "boolean": "^BOOLEAN$", "object": "^OBJECT", "array": "^ARRAY"}


def turns_as_calls(conversations: DataFrame) -> DataFrame:
    """A plain conversation as call and result messages.

    A user turn calls ``reply``, which depends on the call two turns before it and on the opening one; a system turn calls ``configure``;
    an assistant turn is the result of the call one turn before it.
    """
    turn = F.col("turn").cast("long")

    def name(t):
        return F.concat_ws("-", F.lit("call"), t)

    arguments = F.when(F.col("role") == "system", F.to_json(F.struct(F.col("text").alias("instructions")))).otherwise(
        F.to_json(F.struct(F.col("text").alias("prompt"), turn.alias("turn"), F.regexp_count("text", F.lit(WORD)).alias("words")))
    )
    needs = F.array_distinct(F.filter(F.array(F.when(turn >= 2, name(turn - 2)), F.when(turn > 0, name(F.lit(0)))), lambda x: x.isNotNull()))
    call = F.struct(name(turn).alias("id"), F.when(F.col("role") == "system", "configure").otherwise("reply").alias("name"), arguments.alias("arguments"), needs.alias("depends_on"))
    sent = F.to_json(F.struct(F.array(call).alias("tool_calls")))
    got = F.to_json(F.struct(name(turn - 1).alias("tool_call_id"), F.col("text").alias("content")))
    asks = F.col("role").isin("system", "user")
    return conversations.where(F.col("turn").isNotNull() & (asks | (F.col("role") == "assistant"))).select(
        F.col("conv_id").cast("long").alias("conv_id"), turn.alias("turn"), F.when(asks, "assistant").otherwise("tool").alias("role"), F.when(asks, sent).otherwise(got).alias("text")
    )


def _calls(messages: DataFrame) -> DataFrame:
    parsed = messages.where("role = 'assistant'").select("conv_id", "turn", F.inline(F.from_json("text", CALLS)["tool_calls"])).where("id IS NOT NULL")
    first = F.min(F.struct("turn", "name", "arguments", "depends_on"))
    return parsed.groupBy("conv_id", "id").agg(first.alias("first")).select("conv_id", "id", "first.*")


def _results(messages: DataFrame) -> DataFrame:
    parsed = messages.where("role = 'tool'").select("conv_id", "turn", F.from_json("text", RESULT).alias("r")).where("r.tool_call_id IS NOT NULL")
    return parsed.groupBy("conv_id", F.col("r.tool_call_id").alias("id")).agg(F.count(F.lit(1)).alias("n_results"), F.min(F.struct("turn", "r.content"))["content"].alias("result"))


def levels(calls: DataFrame) -> DataFrame:
    """(conv_id, id, level) of every call that stands neither on nor behind a cycle; calls is a cut table with unique (conv_id, id).

    A call's level is the largest of ``low`` and, over its open dependencies, their level plus the dependency's weight. A round
    takes in the dependencies that are done, closes the calls that have none left, and then moves every dependency on a call with a single one
    of its own on to that one, the weights added. Chains so halve in each round; a round that closes no call has only cycles before it.
    """
    key = ["conv", "no_conv"]
    known = calls.select(F.coalesce("conv_id", F.lit(-1)).alias("conv"), F.col("conv_id").isNull().alias("no_conv"), "id", "depends_on")
    needs = known.select(*key, "id", F.explode("depends_on").alias("needs")).distinct()
    real = needs.join(known.select(*key, F.col("id").alias("needs")), [*key, "needs"], "left_semi")
    edges = cut(real.withColumns({"weight": F.lit(1), "owed": F.lit(0)}), "call-edges")
    waiting = cut(edges.select(*key, "id").distinct().withColumn("low", F.lit(0)), "call-waiting")
    done = cut(known.select(*key, "id").join(waiting.select(*key, "id"), [*key, "id"], "left_anti").withColumn("level", F.lit(0)), "call-level")
    out = done
    while not done.isEmpty():
        met = cut(edges.join(done.select(*key, F.col("id").alias("needs"), "level"), [*key, "needs"], "left"), "call-met")
        told = met.groupBy(*key, "id").agg(F.max(F.greatest("owed", F.col("level") + F.col("weight"))).alias("told"), F.sum(F.col("level").isNull().cast("int")).alias("open"))
        state = cut(waiting.join(told, [*key, "id"]).select(*key, "id", F.greatest("low", "told").alias("low"), "open"), "call-state")
        done = cut(state.where("open = 0").select(*key, "id", F.col("low").alias("level")), "call-level")
        left = met.where("level IS NULL").select(*key, "id", "needs", "weight", "owed")
        single = state.where("open = 1").join(left.select(*key, "id", "needs", "weight"), [*key, "id"])
        onward = single.select(*key, F.col("id").alias("needs"), F.col("needs").alias("next"), F.col("weight").alias("more"), F.col("low").alias("at_least"))
        moved = left.join(onward, [*key, "needs"], "left").select(
            *key, "id", F.coalesce("next", "needs").alias("needs"), (F.col("weight") + F.coalesce("more", F.lit(0))).alias("weight"), F.greatest("owed", F.col("weight") + F.col("at_least")).alias("owed")
        )
        fewer = cut(moved.groupBy(*key, "id", "needs").agg(F.max("weight").alias("weight"), F.max("owed").alias("owed")), "call-edges")
        for old in (edges, waiting, met):
            forget(old)
        edges, waiting = fewer, cut(state.where("open > 0").select(*key, "id", "low"), "call-waiting")
        forget(state)
        out = out.unionByName(done)
    return out.select(F.when(~F.col("no_conv"), F.col("conv")).alias("conv_id"), "id", "level")


def violations(tools: dict[str, dict[str, tuple[str, bool]]]):
    """Array of what is wrong with (name, arguments)."""
    value = F.try_parse_json("arguments")
    isobject = F.schema_of_variant(value).startswith("OBJECT")
    out = F.array(F.lit("unknown-tool"))
    for tool, fields in tools.items():
        found = []
        for field, (kind, required) in fields.items():
            path = f"$['{field}']"
            there = F.try_variant_get(value, path, "variant")
            shape = F.schema_of_variant(there)
            empty = there.isNull() | (shape == "VOID")
            found.append(F.when(empty, F.lit(f"missing:{field}") if required else F.lit(None)).when(~shape.rlike(_TYPES[kind]), F.lit(f"type:{field}")))
        extra = F.transform(F.array_sort(F.array_except(F.json_object_keys("arguments"), F.array(*map(F.lit, fields)))), lambda k: F.concat(F.lit("extra:"), k))
        listed = F.concat(F.filter(F.array(*found), lambda x: x.isNotNull()), F.coalesce(extra, F.array().cast("array<string>")))
        out = F.when(F.col("name") == tool, listed).otherwise(out)
    return F.when(~F.coalesce(isobject, F.lit(False)), F.array(F.lit("malformed"))).otherwise(out)


def link(messages: DataFrame, tools: dict[str, dict[str, tuple[str, bool]]]) -> DataFrame:
    """One row for each call: conv_id, turn, id, name, level, problems, dangling, n_results, result, canonical."""
    calls = cut(_calls(messages), "calls")
    ordered = cut(levels(calls), "call-levels")
    same = lambda a, b: a["conv_id"].eqNullSafe(b["conv_id"]) & (a["id"] == b["id"])
    results = cut(_results(messages), "call-results")
    needed = calls.select("conv_id", "id", F.explode("depends_on").alias("needs"))
    missing = needed.alias("n").join(calls.select(F.col("conv_id").alias("c"), F.col("id").alias("i")), F.col("n.conv_id").eqNullSafe(F.col("c")) & (F.col("needs") == F.col("i")), "left_anti")
    dangling = cut(missing.groupBy("conv_id", "id").agg(F.array_sort(F.collect_set("needs")).alias("dangling")), "call-dangling")
    joined = calls
    for other in (ordered, results, dangling):
        joined = joined.join(other, same(joined, other), "left").drop(other["conv_id"], other["id"])
    checked = joined.withColumns({"problems": violations(tools), "n_results": F.coalesce("n_results", F.lit(0)), "dangling": F.coalesce("dangling", F.array().cast("array<string>"))})
    # fields in the order of their names; the variant writes the arguments' keys sorted
    canonical = F.to_json(F.struct(F.try_parse_json("arguments").alias("arguments"), "id", "level", "name", "result"))
    return checked.select("conv_id", "turn", "id", "name", "level", "problems", "dangling", "n_results", "result", canonical.alias("canonical"))


def query(spark, sf_dir):
    linked = link(turns_as_calls(table(spark, sf_dir, "conversations")), TURN_TOOLS)
    status = F.when(F.size("problems") == 0, F.lit("ok")).otherwise(F.array_join("problems", ","))
    return linked.select("conv_id", "turn", F.col("id").alias("call_id"), "name", F.col("level").cast("long").alias("level"), status.alias("status"), "n_results", F.col("canonical"))


SQL = rf"""
WITH RECURSIVE calls AS (
  SELECT conv_id, turn, 'call-' || turn AS id, CASE WHEN role = 'system' THEN 'configure' ELSE 'reply' END AS name, text,
         len(regexp_extract_all(text, '{WORD}')) AS words
  FROM conversations WHERE role IN ('system', 'user')
), edges AS (
  SELECT DISTINCT c.conv_id, c.turn, p.turn AS needs FROM calls c JOIN calls p ON p.conv_id = c.conv_id AND p.turn < c.turn AND (p.turn = c.turn - 2 OR p.turn = 0)
), chains(conv_id, turn, level) AS (
  SELECT conv_id, turn, 0 FROM calls UNION SELECT e.conv_id, e.turn, c.level + 1 FROM chains c JOIN edges e ON e.conv_id = c.conv_id AND e.needs = c.turn
), levels AS (SELECT conv_id, turn, max(level) AS level FROM chains GROUP BY ALL),
results AS (SELECT conv_id, turn - 1 AS turn, count(*) AS n_results, min(text) AS result FROM conversations WHERE role = 'assistant' GROUP BY ALL)
SELECT c.conv_id, c.turn, c.id AS call_id, c.name, l.level::BIGINT AS level, 'ok' AS status, coalesce(n_results, 0) AS n_results,
  '{{"arguments":' || CASE WHEN name = 'configure' THEN json_object('instructions', text) ELSE json_object('prompt', text, 'turn', c.turn, 'words', words) END
  || ',"id":"' || c.id || '","level":' || l.level || ',"name":"' || name || '"' || CASE WHEN result IS NULL THEN '' ELSE ',"result":' || to_json(result) END || '}}' AS canonical
FROM calls c JOIN levels l USING (conv_id, turn) LEFT JOIN results r USING (conv_id, turn)
"""
