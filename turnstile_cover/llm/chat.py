"""Tool-call linking for chat data, in DataFrame functions only.

Assistant messages hold calls as <tool_call>{"id", "name", "arguments"}</tool_call>; a message of
role tool holds {"tool_call_id", "content"}. Calls and results meet in a hash join on conversation
and identifier. A call whose arguments mention "$<id>" depends on that call; calls are ordered by
depth. Arguments are validated against schemas, and each message becomes one line of canonical
JSON (keys sorted, no blanks). Messages stay rows: no conversation is ever gathered in one task.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

from .bitfilter import text_key
from .store import materialize

#: JSON schema types and the prefix of the variant types that satisfy them.
TYPES = {"string": "STRING", "integer": "BIGINT", "number": "BIGINT|DOUBLE|DECIMAL|FLOAT", "boolean": "BOOLEAN", "object": "OBJECT", "array": "ARRAY", "null": "VOID"}
CALL = r"(?s)<tool_call>(.*?)</tool_call>"


def canonical(json: Column) -> Column:
    """JSON text with sorted keys and no blanks; null if it is not JSON."""
    return F.to_json(F.try_parse_json(json))


def quoted(text: Column) -> Column:
    """A JSON string."""
    return F.regexp_extract(F.to_json(F.struct(text.alias("x"))), r"(?s)^\{\"x\":(.*)\}$", 1)


def written(parts: dict[str, Column]) -> Column:
    """A JSON object of values that are JSON already, in the order of its sorted keys."""
    pieces = [x for i, (k, v) in enumerate(sorted(parts.items())) for x in (F.lit(("," if i else "{") + f'"{k}":'), v)]
    return F.concat(*pieces, F.lit("}"))


def meet(left: DataFrame, right: DataFrame, on: list[str], how: str = "left") -> DataFrame:
    """Equi-join in which nulls of the keys are equal; right's keys are dropped."""
    renamed = right.select(*(F.col(c).alias(f"r_{c}") if c in on else F.col(c) for c in right.columns))
    same = [F.col(c).eqNullSafe(F.col(f"r_{c}")) for c in on]
    return left.join(renamed, same, how).drop(*(f"r_{c}" for c in on))


def tool_calls(conversations: DataFrame) -> DataFrame:
    """One row per call of different assistant messages: conv_id, turn, th (of its text), place, id, name, arguments (canonical),
    readable (are they a JSON object), needs (ids). Arguments that are no JSON are kept as a JSON string."""
    spoken = conversations.where((F.col("role") == "assistant") & F.col("text").contains("<tool_call>")).select("conv_id", "turn", text_key().alias("th"), "text")
    spoken = spoken.dropDuplicates(["conv_id", "turn", "th"])  # a repeated message makes its calls once
    bodies = spoken.select("conv_id", "turn", "th", F.posexplode(F.regexp_extract_all("text", F.lit(CALL), F.lit(1))).alias("place", "body")).where(F.try_parse_json("body").isNotNull())
    given = F.coalesce(F.get_json_object("body", "$.arguments"), F.lit("{}"))
    made = bodies.select("conv_id", "turn", "th", "place", F.get_json_object("body", "$.id").alias("id"), F.get_json_object("body", "$.name").alias("name"), F.coalesce(canonical(given), quoted(given)).alias("arguments"))
    made = made.withColumn("readable", F.col("arguments").startswith("{"))
    return made.withColumn("needs", F.array_distinct(F.regexp_extract_all("arguments", F.lit(r'"\$([A-Za-z0-9_-]+)"'), F.lit(1))))


def tool_results(conversations: DataFrame) -> DataFrame:
    """conv_id, id, result_turn, content and n_results; the first result of an identifier counts."""
    rows = conversations.where(F.col("role") == "tool").select("conv_id", "turn", F.get_json_object("text", "$.tool_call_id").alias("id"), F.get_json_object("text", "$.content").alias("content"))
    return rows.where("id is not null").groupBy("conv_id", "id").agg(F.min("turn").alias("result_turn"), F.min_by("content", F.struct("turn", "content")).alias("content"), F.count("*").alias("n_results"))


def argument_faults(schemas: dict[str, dict[str, tuple[str, bool]]]) -> Column:
    """Faults of a call's arguments: not a JSON object, missing, unknown or of another type; only the first without a schema."""
    fault = F.array().cast("array<string>")
    for tool, fields in sorted(schemas.items()):
        values = F.from_json(F.when(F.col("readable"), F.col("arguments")).otherwise("{}"), "map<string,variant>")
        keys = F.map_keys(values)
        checks = [F.array_except(keys, F.array(*map(F.lit, sorted(fields))).cast("array<string>"))]
        checks[0] = F.transform(checks[0], lambda k: F.concat(F.lit("unknown:"), k))
        for name, (kind, required) in sorted(fields.items()):
            value = F.element_at(values, F.lit(name))
            wrong = F.array_contains(keys, name) & ~F.schema_of_variant(value).rlike(f"^({TYPES[kind]})")
            missing = F.lit(required) & ~F.array_contains(keys, name)
            checks.append(F.when(missing, F.array(F.lit(f"missing:{name}"))).when(wrong, F.array(F.lit(f"type:{name}"))).otherwise(F.array().cast("array<string>")))
        fault = F.when(F.col("name") == tool, F.concat(*checks)).otherwise(fault)
    return F.when(~F.col("readable"), F.array(F.lit("not_json"))).otherwise(fault)


def ordered_calls(calls: DataFrame) -> DataFrame:
    """calls with depth: 0 without needs inside the conversation, else one more than the deepest; null on a cycle or after one.

    Level by level: a round keeps only the needs still open, and writes the calls that it freed, so all rounds together
    write each need as often as it is deep and each call once.
    """
    key = ["conv_id", "id"]
    known = calls.select(*key).where("id is not null").distinct()
    needs = calls.select(*key, F.explode("needs").alias("need")).where("id is not null").distinct()
    open_ = materialize(meet(needs, known.withColumnRenamed("id", "need"), ["conv_id", "need"], "left_semi"), "chat-needs")
    levels = [materialize(meet(known, open_.select(*key).distinct(), key, "left_anti").withColumn("depth", F.lit(0)), "chat-level")]
    while not open_.isEmpty():
        left = materialize(meet(open_, levels[-1].select("conv_id", F.col("id").alias("need")), ["conv_id", "need"], "left_anti"), "chat-needs")
        freed = materialize(meet(open_.select(*key).distinct(), left.select(*key).distinct(), key, "left_anti").withColumn("depth", F.lit(len(levels))), "chat-level")
        if freed.isEmpty():
            break
        levels.append(freed)
        open_ = left
    return meet(calls, reduce(DataFrame.unionByName, levels), key)


def format_chats(conversations: DataFrame, schemas: dict[str, dict[str, tuple[str, bool]]] | None = None) -> DataFrame:
    """Per message: conv_id, turn, role, n_calls, n_linked, n_faulty, is_orphan and line (canonical JSON).

    Calls of a message are listed by depth, then place; those on a cycle or without an id come last, with depth -1. A result
    without a call is an orphan; so is one without an identifier. A null conv_id is one conversation, a null turn one turn.
    Null texts and roles are empty strings in the line. Repeated rows give repeated lines with the same calls; two texts of
    one turn have their own. Arguments that are no JSON object are the fault not_json; a call that is not JSON stays text.
    """
    rows = conversations.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    calls = materialize(tool_calls(rows), "chat-calls")
    linked = meet(ordered_calls(calls), tool_results(rows), ["conv_id", "id"]).withColumn("faults", argument_faults(schemas or {}))
    faults = F.array_join(F.transform("faults", quoted), ",")
    parts = {"arguments": F.col("arguments"), "depth": F.coalesce("depth", F.lit(-1)).cast("string"), "faults": F.concat(F.lit("["), faults, F.lit("]"))}
    parts |= {"id": quoted(F.coalesce("id", F.lit(""))), "name": quoted(F.coalesce("name", F.lit(""))), "result": quoted(F.coalesce("content", F.lit("")))}
    ranked = F.struct(F.coalesce("depth", F.lit(2**31 - 1)).alias("d"), F.col("place"), written(parts).alias("json"))
    by_message = linked.groupBy("conv_id", "turn", "th").agg(F.count("*").alias("n_calls"), F.count("n_results").alias("n_linked"), F.count_if(F.size("faults") > 0).alias("n_faulty"), F.array_sort(F.collect_list(ranked)).alias("calls"))
    orphan_key = F.when(F.col("role") == "tool", F.coalesce(F.get_json_object("text", "$.tool_call_id"), F.lit(""))).otherwise(F.concat(F.lit("\0"), F.coalesce(F.col("turn").cast("string"), F.lit(""))))
    keyed = rows.withColumns({"answers": orphan_key, "th": F.when((F.col("role") == "assistant") & F.col("text").contains("<tool_call>"), text_key())})
    called = calls.where("id is not null").select("conv_id", F.col("id").alias("answers"), F.lit(True).alias("called")).distinct()
    joined = meet(meet(keyed, by_message, ["conv_id", "turn", "th"]), called, ["conv_id", "answers"])
    mine = F.when(F.col("role") == "assistant", F.col("calls"))
    listed = F.coalesce(F.array_join(F.transform(mine, lambda c: c["json"]), ","), F.lit(""))
    parts = {"content": quoted(F.col("text")), "conv_id": F.coalesce(F.col("conv_id").cast("string"), F.lit("null")), "role": quoted(F.col("role")), "tool_calls": F.concat(F.lit("["), listed, F.lit("]")), "turn": F.coalesce(F.col("turn").cast("string"), F.lit("null"))}
    line = written(parts)
    count = lambda c: F.when(F.col("role") == "assistant", F.coalesce(c, F.lit(0))).otherwise(0).cast("long").alias(c)
    orphan = ((F.col("role") == "tool") & F.col("called").isNull()).alias("is_orphan")
    return joined.select("conv_id", "turn", "role", count("n_calls"), count("n_linked"), count("n_faulty"), orphan, line.alias("line"))
