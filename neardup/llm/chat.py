"""Chat formatting with tool-call linking, in DataFrame functions only.

A turn's text may be a JSON object that holds ``tool_calls`` (each with ``id``, ``name``, ``arguments`` and,
if it needs other calls first, ``after``: their ids) or a ``tool_call_id`` with ``content`` (a result).
Calls and results are hash-joined by conversation and identifier. Turns are ordered topologically: a result
stands at the level of its call, a call above all that it needs, every other turn at its own turn number;
equal levels keep the order of turns. Calls whose needs are all placed are placed round by round, on the
calls alone and for as many rounds as the longest chain has; calls never placed are on a cycle, or behind
one: they keep their own turn and are marked. Arguments are checked against a schema for each tool.

Each turn becomes one row of canonical JSON (keys sorted, no white space); a conversation of any length is
never gathered into one task or row.

Defined cases: a null text is empty content; null ids, turns and roles stay null and sort first; text that is
no such JSON object, or whose fields have other types, is an ordinary message; of several calls with one id
in a conversation the first (by turn, then place) is linked and the later ones are marked ``repeated``;
results without a call are marked ``orphan``, calls without a result ``unanswered``; repeated rows stay;
extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from neardup.sources.lineage import drop_written, written

#: Tools and their arguments: (name, JSON type, required).
SCHEMAS = {
    "search": [("query", "string", True), ("limit", "integer", False)],
    "calculate": [("expression", "string", True)],
    "fetch": [("url", "string", True), ("timeout", "number", False), ("follow", "boolean", False)],
}
_SHAPE = (
    "struct<tool_calls:array<struct<id:string,name:string,arguments:variant,after:array<string>>>,"
    "tool_call_id:string,content:variant>"
)
#: What a JSON type looks like as ``schema_of_variant`` says; fixed values.
_TYPES = {
    "string": "^STRING$",
    "integer": "^BIGINT$",
    "number": "^(BIGINT|DOUBLE|DECIMAL.*)$",
    "boolean": "^BOOLEAN$",
    "object": "^OBJECT.*$",
    "array": "^ARRAY.*$",
}


def _fault(name: Column, arguments: Column, schemas: dict) -> Column:
    """What is wrong with a call's arguments, or null."""
    field = lambda a: F.try_variant_get(arguments, f"$.{a}", "variant")
    out = F.lit("unknown tool")
    for tool, wanted in schemas.items():
        first = F.lit(None).cast("string")
        for a, kind, required in reversed(wanted):
            fits = F.schema_of_variant(field(a)).rlike(_TYPES[kind])
            if kind == "integer":  # 2.0 is one: it is written as 2
                fits = fits | (F.schema_of_variant(field(a)).rlike("^(DOUBLE|DECIMAL.*)$") & (F.try_variant_get(arguments, f"$.{a}", "double") % 1 == 0))
            wrong = F.when(field(a).isNotNull() & ~F.coalesce(fits, F.lit(False)), F.lit(f"{a} is no {kind}"))
            missing = F.when(field(a).isNull(), F.lit(f"{a} is missing")) if required else F.lit(None).cast("string")
            first = F.coalesce(missing, wrong, first)
        given = F.map_keys(F.try_variant_get(arguments, "$", "map<string,variant>"))
        others = F.array_sort(F.array_except(given, F.array(*(F.lit(a) for a, _, _ in wanted)).cast("array<string>")))
        first = F.coalesce(first, F.when(F.size(others) > 0, F.concat(F.array_join(others, ", "), F.lit(" undeclared"))))
        shape = F.when(~F.coalesce(F.schema_of_variant(arguments), F.lit("")).startswith("OBJECT"), F.lit("arguments are no object"))
        out = F.when(name == tool, F.coalesce(shape, first)).otherwise(out)
    return out


def format_turns(turns: DataFrame, schemas: dict | None = None) -> DataFrame:
    """One row per row of ``turns(conv_id, turn, role, text)``: ``conv_id, turn, level, kind, status, json``.

    Rows sort by ``level``, then ``turn``, within a conversation; ``status`` lists what linking and checking found.
    """
    schemas = SCHEMAS if schemas is None else schemas
    looks = F.col("text").rlike(r"(?s)^\s*\{.*\"tool_call")
    body = F.when(looks & F.try_parse_json("text").isNotNull(), F.from_json("text", _SHAPE))
    rows = turns.select("conv_id", "turn", "role", "text", body.alias("body"))
    plain = F.col("body.tool_calls").isNull() & F.col("body.tool_call_id").isNull()
    kind = F.when(F.col("body").isNull() | plain, "message").when(F.col("body.tool_calls").isNotNull(), "call").otherwise("result")
    rows = written(rows.withColumn("kind", kind))
    calls = rows.where("kind = 'call'").select("conv_id", "turn", F.posexplode("body.tool_calls").alias("place", "c"))
    special = written(
        calls.where("c.id is not null")
        .groupBy("conv_id", F.col("c.id").alias("id"))
        .agg(F.min(F.struct("turn", "place", F.col("c.after").alias("after"))).alias("c"), F.count("*").alias("uses"))
        .select("conv_id", "id", "c.turn", F.coalesce(F.col("c.turn"), F.lit(0)).cast("long").alias("level"), "c.after", "uses")
    )
    ids = special.select("conv_id", F.col("id").alias("needs"))
    links = written(special.select("conv_id", "id", F.explode("after").alias("needs")).distinct().join(ids, ["conv_id", "needs"]))
    unmet = links.groupBy("conv_id", "id").agg(F.count("*").alias("unmet"))
    levels = special.select("conv_id", "id", "level").join(unmet, ["conv_id", "id"], "left").withColumn("unmet", F.coalesce("unmet", F.lit(0)))
    levels = levels.withColumn("fresh", F.col("unmet") == 0)
    if not links.isEmpty():
        levels = written(levels)
        while not levels.where("fresh").isEmpty():
            needed = levels.where("fresh").select("conv_id", F.col("id").alias("needs"), F.col("level").alias("at"))
            met = links.join(needed, ["conv_id", "needs"]).groupBy("conv_id", "id").agg((F.max("at") + 1).alias("least"), F.count("*").alias("met"))
            left = F.col("unmet") - F.coalesce("met", F.lit(0))
            after = written(
                levels.drop("fresh")
                .join(met, ["conv_id", "id"], "left")
                .select("conv_id", "id", F.greatest("level", F.coalesce("least", "level")).alias("level"), left.alias("unmet"), ((F.col("unmet") > 0) & (left == 0)).alias("fresh"))
            )
            drop_written(levels)
            levels = after
    # What was never placed is on a cycle or behind one.
    cycle = F.col("unmet") > 0
    own_turn = special.select("conv_id", "id", F.col("level").alias("own"))
    placed = levels.join(own_turn, ["conv_id", "id"]).select("conv_id", "id", F.when(cycle, F.col("own")).otherwise(F.col("level")).alias("at"), cycle.alias("cycle"))
    known = special.select("conv_id", "id", F.col("turn").alias("call_turn"), "uses").join(placed, ["conv_id", "id"])
    results = rows.where("kind = 'result'").select("conv_id", F.col("body.tool_call_id").alias("id"))
    answered = results.distinct().withColumn("answered", F.lit(True))
    linked = written(known.join(answered, ["conv_id", "id"], "left"))
    # Calls: one row per turn that holds any. Turns of a conversation may repeat, so this joins on both.
    by_turn = (
        calls.withColumn("id", F.col("c.id"))
        .withColumn("fault", _fault(F.col("c.name"), F.col("c.arguments"), schemas))
        .join(linked, ["conv_id", "id"], "left")
        .groupBy("conv_id", "turn")
        .agg(
            F.max("at").alias("at"),
            F.array_sort(F.collect_set(F.concat_ws(": ", F.coalesce("id", F.lit("no id")), "fault"))).alias("faults"),
            F.max(F.col("fault").isNotNull() | F.col("id").isNull()).alias("invalid"),
            F.max(F.coalesce(F.col("answered"), F.lit(False)) == F.lit(False)).alias("unanswered"),
            F.max(F.coalesce(F.col("uses") > 1, F.lit(False))).alias("repeated"),
            F.max(F.coalesce("cycle", F.lit(False))).alias("cycle"),
        )
    )
    out_calls = (
        rows.where("kind = 'call'")
        .join(by_turn.select(F.col("conv_id").alias("c"), F.col("turn").alias("t"), "at", "faults", "invalid", "unanswered", "repeated", "cycle"),
              F.col("conv_id").eqNullSafe(F.col("c")) & F.col("turn").eqNullSafe(F.col("t")), "left")
        .drop("c", "t")
    )
    out_results = (
        rows.where("kind = 'result'")
        .withColumn("id", F.col("body.tool_call_id"))
        .join(linked.select("conv_id", "id", "at"), ["conv_id", "id"], "left")
    )
    own = F.coalesce("turn", F.lit(0)).cast("long")
    flag = lambda c, name: F.when(F.coalesce(F.col(c), F.lit(False)), name)
    pair = lambda k, v: F.concat(F.lit(f'"{k}":'), v)
    quoted = lambda c: F.regexp_extract(F.to_json(F.struct(F.coalesce(F.col(c), F.lit("")).alias("v"))), r"(?s)^\{\"v\":(.*)\}$", 1)
    number = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("null"))

    def joined(parts: dict[str, Column]) -> Column:
        return F.concat(F.lit("{"), F.concat_ws(",", *(parts[k] for k in sorted(parts))), F.lit("}"))

    head = {"conv_id": pair("conv_id", number("conv_id")), "role": pair("role", quoted("role")), "turn": pair("turn", number("turn"))}
    messages = rows.where("kind = 'message'").select(
        "conv_id", "turn", own.alias("level"), "kind", F.lit("").alias("status"), joined(head | {"content": pair("content", quoted("text"))}).alias("json")
    )
    tool_calls = F.to_json(F.variant_get(F.try_parse_json("text"), "$.tool_calls", "variant"))
    done_calls = out_calls.select(
        "conv_id",
        "turn",
        F.coalesce("at", own).alias("level"),
        "kind",
        F.concat_ws(
            "; ", flag("invalid", "invalid"), F.when(F.size(F.filter("faults", lambda f: f.contains(": "))) > 0, F.array_join(F.filter("faults", lambda f: f.contains(": ")), ", ")),
            flag("unanswered", "unanswered"), flag("repeated", "repeated"), flag("cycle", "cycle"),
        ).alias("status"),
        joined(head | {"tool_calls": pair("tool_calls", tool_calls)}).alias("json"),
    )
    done_results = out_results.select(
        "conv_id",
        "turn",
        # after its call even where the turns say otherwise
        F.greatest(own, F.coalesce("at", own)).alias("level"),
        "kind",
        F.when(F.col("at").isNull(), "orphan").otherwise("").alias("status"),
        joined(
            head
            | {
                "content": pair("content", F.coalesce(F.to_json(F.col("body.content")), F.lit('""'))),
                "tool_call_id": pair("tool_call_id", F.regexp_extract(F.to_json(F.struct(F.col("id").alias("v"))), r"(?s)^\{\"v\":(.*)\}$", 1)),
            }
        ).alias("json"),
    )
    return reduce(DataFrame.union, [messages, done_calls, done_results])
