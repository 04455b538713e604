"""Chat formatting: tool-call linking.

Turns whose text is a JSON object are read as tool traffic; all others are plain messages.

- ``{"tools": [{"name", "required": [..], "types": {argument: JSON type}}]}`` declares the tools of a conversation;
- ``{"content"?, "tool_calls": [{"id", "name", "arguments": {..}, "after": [ids]}]}`` makes calls, which may wait for
  the results of other calls of the conversation (``after``);
- ``{"tool_call_id", "content"}`` is the result of a call.

Calls and results are joined by (conversation, identifier); calls are ordered topologically: ``level`` 0 waits for
nothing, any other is one more than the highest it waits for. Arguments are validated against the declared schema.
Every message, call and result is serialised as canonical JSON: keys sorted, no white space.

Native: parsing, validation and serialisation are built-in expressions (JSON and variant functions); linking is an
equi-join; the order is found by pointer jumping along chains, then by peeling what waits for several calls. The result has a row per item, sorted by
(turn, level, item) within a conversation: a conversation is never gathered into one row or task, so one with
a third of all turns is dealt out like any other.

Defined results: null or empty text is a message without content or with an empty one. Rows with a null conv_id are one conversation.
Of calls that repeat an identifier in
a conversation, the first by (turn, item) is linked, later ones get the error ``duplicate_id``. Of a call's results the first by turn that does not
come before the call answers it; others get ``repeated_result``, and one in an earlier turn than its call gets ``early_result`` and answers nothing. Other errors:
``no_id``, ``no_result``, ``unknown_tool``, ``bad_arguments``, ``missing:name``, ``type:name``, ``unknown_dependency``,
``cycle`` (also for what waits on a cycle; level null), ``orphan`` (a result without call). A null turn comes before all others. Text that begins like an object but
isn't one that is described here is a message. Repeated rows are separate items. An empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, store, table

CALL = "struct<id:string,name:string,arguments:string,after:array<string>>"
TOOL = "struct<name:string,required:array<string>,types:map<string,string>>"
SHAPE = f"tools array<{TOOL}>, tool_calls array<{CALL}>, tool_call_id string, content string"
#: JSON type -> expression over the type name that Spark gives a variant; fixed values
JSON_TYPES = {
    "string": "^STRING",
    "integer": "^(BIGINT|INT|SMALLINT|TINYINT)",
    "number": "^(BIGINT|INT|SMALLINT|TINYINT|DECIMAL|DOUBLE|FLOAT)",
    "boolean": "^BOOLEAN",
    "array": "^ARRAY",
    "object": "^OBJECT",
    "null": "^VOID",
}


def _canonical(json: Column) -> Column:
    """Canonical form of a JSON text; null if it isn't JSON. A variant keeps the keys of objects sorted."""
    return F.to_json(F.try_parse_json(json))


def items(turns: DataFrame) -> DataFrame:
    """One row per message, call, result and declaration of a table (conv_id, turn, role, text)."""
    text = F.col("text")
    parsed = F.when(text.rlike(r"^\s*\{") & F.try_parse_json(text).isNotNull(), F.from_json(text, SHAPE))
    known = "p.tools is not null or p.tool_calls is not null or p.tool_call_id is not null"
    marked = turns.select("conv_id", "turn", "role", "text", parsed.alias("p")).withColumn("tooled", F.coalesce(F.expr(known), F.lit(False)))
    item = "struct<item:int,kind:string,call_id:string,name:string,arguments:string,after:array<string>,content:string,tool:" + TOOL + ">"
    blank = {"call_id": "string", "name": "string", "arguments": "string", "after": "array<string>", "content": "string", "tool": TOOL}

    def made(kind: str, at: Column, **values: Column) -> Column:
        fields = [values.get(k, F.lit(None)).cast(t).alias(k) for k, t in blank.items()]
        return F.struct(at.cast("int").alias("item"), F.lit(kind).alias("kind"), *fields)

    none = F.array().cast(f"array<{item}>")
    message = F.when(
        ~F.col("tooled") | (F.col("p.tool_calls").isNotNull() & F.col("p.content").isNotNull()),
        F.array(made("message", F.lit(0), content=F.when(F.col("tooled"), F.col("p.content")).otherwise(text))),
    ).otherwise(none)
    calls = F.when(
        F.col("tooled"),
        F.transform(
            "p.tool_calls",
            lambda c, i: made("call", i + 1, call_id=c["id"], name=c["name"], arguments=c["arguments"], after=c["after"]),
        ),
    )
    result = F.when(
        F.col("tooled") & F.col("p.tool_call_id").isNotNull(),
        F.array(made("result", F.lit(0), call_id=F.col("p.tool_call_id"), content=F.col("p.content"))),
    )
    tools = F.when(
        F.col("tooled"), F.transform("p.tools", lambda t, i: made("tool", i + 1, name=t["name"], tool=t))
    )
    every = F.concat(message, *[F.coalesce(x, none) for x in (calls, result, tools)])
    return marked.select("conv_id", "turn", "role", F.explode(every).alias("i")).select("conv_id", "turn", "role", "i.*")


def levels(calls: DataFrame, waits: DataFrame) -> DataFrame:
    """uid and level of the calls (uid) that no cycle holds up; ``waits``: uid waits for other, both known calls.

    A call that waits for one other is a link of a chain: pointer jumping finds, in as many rounds as the chain's length has bits, the call
    at the chain's start and how far it is. Calls that wait for several are then peeled, one round for each of them in a row.
    """
    edges = store(waits.select("uid", "other").distinct(), "tc-waits")
    many = store(edges.df.groupBy("uid").agg(F.count(F.lit(1)).alias("k")), "tc-many")
    free = calls.select("uid").join(many.df, "uid", "left_anti")
    chain = store(edges.df.join(many.df.where("k = 1").select("uid"), "uid").select("uid", F.col("other").alias("at"), F.lit(1).cast("long").alias("far")), "tc-chain")
    rounds, links = 0, chain.df.count()
    while links and (1 << rounds) <= 2 * links:
        step = chain.df.select(F.col("uid").alias("at"), F.col("at").alias("next"), F.col("far").alias("more"))
        after = store(
            chain.df.join(step, "at", "left").select("uid", F.coalesce("next", "at").alias("at"), (F.col("far") + F.coalesce("more", F.lit(0))).alias("far"), F.col("next").isNotNull().alias("moved")),
            "tc-chain",
        )
        chain.drop()
        chain, rounds = after, rounds + 1
        if not after.df.where("moved").limit(1).count():
            break
    # what still points into a chain goes round in a cycle
    ends = chain.df.select("uid", "at", "far").join(chain.df.select(F.col("uid").alias("at")), "at", "left_anti")
    wide = edges.df.join(many.df.where("k > 1").select("uid"), "uid")
    # a dependency on a link of a chain is one on the chain's start, that much further
    inside = chain.df.select(F.col("uid").alias("other"))
    hops = wide.join(inside, "other", "left_anti").select("uid", F.col("other").alias("at"), F.lit(0).cast("long").alias("far")).union(
        wide.join(ends.select(F.col("uid").alias("other"), "at", "far"), "other").select("uid", "at", "far")
    )
    lost = wide.join(inside, "other", "left_semi").join(ends.select(F.col("uid").alias("other")), "other", "left_anti").select("uid").distinct()
    hops = store(hops.join(lost, "uid", "left_anti"), "tc-hops")
    known = store(free.select("uid", F.lit(0).cast("long").alias("level")), "tc-level")
    while True:
        met = hops.df.join(known.df.select(F.col("uid").alias("at"), "level"), "at", "left").join(known.df.select("uid"), "uid", "left_anti")
        ready = store(
            met.groupBy("uid").agg(F.count_if(F.col("level").isNull()).alias("open"), (F.max(F.col("level") + F.col("far")) + 1).alias("level")).where("open = 0").select("uid", "level"),
            "tc-ready",
        )
        if not ready.df.limit(1).count():
            break
        more = store(known.df.union(ready.df), "tc-level")
        known.drop()
        known = more
    tails = ends.join(known.df.select(F.col("uid").alias("at"), "level"), "at").select("uid", (F.col("level") + F.col("far")).alias("level"))
    return store(known.df.union(tails).select("uid", F.col("level").cast("int").alias("level")), "tc-order").df


def _argument_errors(arguments: Column, tool: Column) -> Column:
    """array<string> of what is wrong with a call's arguments."""
    given = F.from_json(arguments, "map<string,variant>")
    keys = F.coalesce(F.map_keys(given), F.array().cast("array<string>"))
    missing = F.transform(
        F.array_except(F.coalesce(tool["required"], F.array().cast("array<string>")), keys),
        lambda k: F.concat(F.lit("missing:"), k),
    )
    patterns = F.create_map(*[F.lit(x) for pair in JSON_TYPES.items() for x in pair])
    wrong = F.filter(
        F.map_entries(tool["types"]),
        lambda e: F.array_contains(keys, e["key"])
        & ~F.coalesce(F.regexp(F.schema_of_variant(F.try_element_at(given, e["key"])), F.try_element_at(patterns, e["value"])), F.lit(False)),
    )
    types = F.coalesce(F.transform(wrong, lambda e: F.concat(F.lit("type:"), e["key"])), F.array().cast("array<string>"))
    bad = arguments.isNotNull() & F.coalesce(~F.schema_of_variant(F.try_parse_json(arguments)).startswith("OBJECT"), F.lit(True))
    return (
        F.when(tool.isNull(), F.array(F.lit("unknown_tool")))
        .when(bad, F.array(F.lit("bad_arguments")))
        .otherwise(F.concat(F.array_sort(missing), F.array_sort(types)))
    )


def _json(kind: Column) -> Column:
    """Canonical JSON of an item: fields in the order of their names, absent ones left out."""
    message = F.to_json(F.struct("content", "conv_id", "role", "turn"))
    result = F.to_json(F.struct("content", F.col("call_id").alias("tool_call_id")))
    call = F.to_json(
        F.struct(
            F.array_sort("after").alias("after"),
            F.try_parse_json("arguments").alias("arguments"),
            F.col("call_id").alias("id"),
            "level",
            "name",
        )
    )
    tool = F.to_json(F.struct("name", F.array_sort("tool.required").alias("required"), F.try_parse_json(F.to_json("tool.types")).alias("types")))
    return F.when(kind == "call", call).when(kind == "result", result).when(kind == "tool", tool).otherwise(message)


def link_tool_calls(turns: DataFrame) -> DataFrame:
    """One row per item of the conversations, linked, ordered, validated and serialised."""
    # joins go by a name that a null conversation has too
    numbered = items(turns).withColumns({"uid": F.monotonically_increasing_id(), "conv": F.to_json(F.struct("conv_id"))})
    every = materialise(numbered, "tc-items")
    traffic = every.where("kind in ('call', 'result', 'tool')")
    if not traffic.limit(1).count():
        plain = every.withColumns({"level": F.lit(None).cast("int"), "linked_turn": F.lit(None).cast("bigint"), "errors": F.lit("")})
        return _shown(plain)
    calls = every.where("kind = 'call'")
    first = store(
        calls.where("call_id is not null").groupBy("conv", "call_id").agg(
            F.min(F.struct("turn", "item", "uid")).alias("f")
        ).select("conv", "call_id", F.col("f.uid").alias("call_uid"), F.col("f.turn").alias("call_turn")),
        "tc-first",
    ).df
    early = F.coalesce(F.col("turn"), F.lit(-(1 << 62))) < F.coalesce(F.col("call_turn"), F.lit(-(1 << 62)))
    answers = store(
        every.where("kind = 'result'")
        .join(first, ["conv", "call_id"])
        .where(~early)
        .groupBy("conv", "call_id")
        .agg(F.min(F.struct("turn", "uid")).alias("a"))
        .select("conv", "call_id", F.col("a.turn").alias("answer_turn"), F.col("a.uid").alias("answer_uid")),
        "tc-answers",
    ).df
    tools = store(
        every.where("kind = 'tool'").groupBy("conv", "name").agg(F.min_by("tool", F.struct("turn", "item", "uid")).alias("declared")),
        "tc-tools",
    ).df
    named = calls.join(first, ["conv", "call_id"], "left")
    asked = named.where("uid = call_uid").select("conv", "uid", F.explode(F.array_distinct("after")).alias("call_id"))
    waits = store(asked.join(first, ["conv", "call_id"], "left").select("uid", F.col("call_uid").alias("other")), "tc-asked").df
    lost = waits.where("other is null").select("uid").distinct().withColumn("lost", F.lit(True))
    order = levels(named.where("uid = call_uid"), waits.where("other is not null"))
    judged = (
        named.join(answers, ["conv", "call_id"], "left")
        .join(tools, ["conv", "name"], "left")
        .join(order, "uid", "left")
        .join(lost, "uid", "left")
    )
    flag = lambda when, what: F.when(when, F.array(F.lit(what))).otherwise(F.array().cast("array<string>"))
    twice = F.col("call_uid").isNotNull() & (F.col("uid") != F.col("call_uid"))
    errors = F.concat(
        flag(F.col("call_id").isNull(), "no_id"),
        flag(twice, "duplicate_id"),
        _argument_errors(F.col("arguments"), F.col("declared")),
        flag(F.col("lost").isNotNull(), "unknown_dependency"),
        flag(F.col("level").isNull() & ~twice & F.col("call_id").isNotNull(), "cycle"),
        flag(F.col("answer_uid").isNull(), "no_result"),
    )
    names = every.columns
    made_calls = judged.select(*names, "level", F.when(~twice, F.col("answer_turn")).alias("linked_turn"), F.array_join(errors, ",").alias("errors"))
    wrong = (
        F.when(F.col("call_uid").isNull(), "orphan")
        .when(early, "early_result")
        .when(F.col("answer_uid").isNotNull() & (F.col("answer_uid") != F.col("uid")), "repeated_result")
        .otherwise("")
    )
    results = (
        every.where("kind = 'result'")
        .join(first, ["conv", "call_id"], "left")
        .join(answers, ["conv", "call_id"], "left")
        .join(order.withColumnRenamed("uid", "call_uid"), "call_uid", "left")
        .select(*names, "level", F.when(~early, F.col("call_turn")).alias("linked_turn"), wrong.alias("errors"))
    )
    others = every.where("kind in ('message', 'tool')").select(
        *names, F.lit(None).cast("int").alias("level"), F.lit(None).cast("bigint").alias("linked_turn"), F.lit("").alias("errors")
    )
    return _shown(others.unionByName(made_calls).unionByName(results))


def _shown(rows: DataFrame) -> DataFrame:
    return rows.select(
        "conv_id", "turn", "item", "role", "kind", "call_id", "name", "level", F.col("linked_turn").cast("bigint").alias("linked_turn"), "errors", _json(F.col("kind")).alias("json")
    )


#: The given conversations hold no JSON, so each of their turns is a message; the call logic is tested on fixtures.
ORACLE_SQL = r"""
SELECT conv_id, turn, CAST(0 AS INTEGER) AS item, role, 'message' AS kind, CAST(NULL AS VARCHAR) AS call_id,
       CAST(NULL AS VARCHAR) AS name, CAST(NULL AS INTEGER) AS level, CAST(NULL AS BIGINT) AS linked_turn, '' AS errors,
       '{' || coalesce('"content":"' || replace(replace(replace(replace(text, '\', '\\'), '"', '\"'), chr(10), '\n'), chr(9), '\t') || '",', '')
       || '"conv_id":' || conv_id || ',' || coalesce('"role":"' || role || '",', '') || '"turn":' || turn || '}' AS json
FROM conversations
"""


def op3_tool_call_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_tool_calls(table(spark, sf_dir, "conversations"))
