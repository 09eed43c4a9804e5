"""Chat formatting of tool calls, with built-in SQL functions only.

Calls and results are hash-joined by identifier, after each side is folded to the earliest of
an identifier so that a repeated one can't multiply rows; arguments are validated against the
tools' schemas; messages are ordered so that a result follows its call and a call follows the
results it refers to; each message becomes one line of canonical JSON (keys sorted, no spaces).
Places within a conversation come from a range sort and counts by partition, so a conversation
that holds a third of all rows is spread over tasks.

Defined cases: a null text is a null content; a null role is a message; a null conversation or
turn sorts first; a call or result without identifier is never linked; repeated identifiers
beyond the earliest are `repeated`; references in a circle, or to a call in or behind one,
keep turn order and are `circular`; a null reference is none; a reference to nothing waits for nothing;
arguments that aren't a JSON object are invalid; an empty table gives an empty result; other
columns are ignored; rows with one conversation and turn stay apart.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from webgather.llm._shared import written

#: Schemas of tools: for each argument its JSON type as schema_of_variant names it, and whether it must be there.
Schemas = dict[str, dict[str, tuple[str, bool]]]


def canonical(json: Column) -> Column:
    """JSON text with sorted keys and no spaces, null if it can't be parsed."""
    return F.to_json(F.try_parse_json(json))


def valid_arguments(name: Column, arguments: Column, schemas: Schemas) -> Column:
    """Whether the arguments are an object with every needed key, no unknown key, and the types asked for."""
    value = F.try_parse_json(arguments)
    out = F.lit(False)
    for tool, fields in schemas.items():
        keys = F.json_object_keys(arguments)
        ok = F.coalesce(F.size(F.array_except(keys, F.array(*(F.lit(k) for k in fields)))) == 0, F.lit(False))
        for key, (kind, needed) in fields.items():
            own = F.schema_of_variant(F.try_variant_get(value, f"$.{key}", "variant"))
            fits = own == kind
            ok = ok & F.coalesce(fits, F.lit(not needed))
        out = F.when(name == tool, ok).otherwise(out)
    return out


def links(calls: DataFrame, results: DataFrame) -> DataFrame:
    """conv_id, call_id, call_turn, result_turn of each identifier, on whichever side it is."""
    folded = [t.filter("call_id is not null").groupBy("conv_id", "call_id").agg(F.min("turn").alias(f"{n}_turn")) for t, n in ((calls, "call"), (results, "result"))]
    return folded[0].join(folded[1].hint("shuffle_hash"), ["conv_id", "call_id"], "full_outer")


def levels(needs: DataFrame, found: DataFrame) -> DataFrame:
    """conv_id, call_id, level, at: the longest chain of references before a call and the turn it stands at; null in or behind a circle.

    needs: (conv_id, call_id, needed); found: what links() gives. A call stands at the latest of
    its own turn and, for all it needs, where they and their results stand. Each round settles
    the calls whose needs are settled, until a round settles none.
    """
    needs = written(needs.distinct())
    if needs.isEmpty():
        return needs.select("conv_id", "call_id", F.lit(0).alias("level"), F.lit(0).cast("long").alias("at")).limit(0)
    callers = needs.select("conv_id", "call_id").distinct()
    named = needs.select("conv_id", F.col("needed").alias("call_id")).unionByName(callers).distinct()
    turns = written(named.join(found, ["conv_id", "call_id"], "left").select("conv_id", "call_id", "call_turn", "result_turn"))
    free = turns.join(callers, ["conv_id", "call_id"], "left_anti")
    free = written(free.select("conv_id", "call_id", F.lit(0).alias("level"), F.col("call_turn").alias("at"), F.greatest("call_turn", "result_turn").alias("answered")))
    level, done = free, free.count()
    while True:
        ready = (
            needs.join(level.select("conv_id", F.col("call_id").alias("needed"), "level", "answered"), ["conv_id", "needed"], "left")
            .groupBy("conv_id", "call_id")
            .agg((F.max("level") + 1).alias("level"), F.max("answered").alias("_late"), F.count_if(F.col("level").isNull()).alias("open"))
            .filter("open = 0")
            .join(turns, ["conv_id", "call_id"])
            .withColumn("at", F.greatest("call_turn", "_late"))
            .select("conv_id", "call_id", "level", "at", F.greatest("at", "result_turn").alias("answered"))
        )
        level = written(free.unionByName(ready))
        n = level.count()
        if n == done:
            break
        done = n
    return callers.join(level.select("conv_id", "call_id", "level", "at"), ["conv_id", "call_id"], "left")


def placed(rows: DataFrame, group: str, order: list[str], name: str = "position") -> DataFrame:
    """rows with their 0-based place within the group, by range partitions and counts."""
    spread = written(rows.repartitionByRange(group, *order).withColumn("_part", F.spark_partition_id()))
    local = spread.withColumn("_k", F.row_number().over(Window.partitionBy(group, "_part").orderBy(*order)))
    before = Window.partitionBy(group).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = spread.groupBy(group, "_part").agg(F.count(F.lit(1)).alias("_n")).select(F.col(group).alias("_g"), F.col("_part").alias("_p"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    return local.join(base, local[group].eqNullSafe(base["_g"]) & (local["_part"] == base["_p"])).withColumn(name, F.col("_base") + F.col("_k") - 1).drop("_g", "_p", "_base", "_part", "_k", "_n")


def format_calls(messages: DataFrame, schemas: Schemas) -> DataFrame:
    """conv_id, turn, position, kind, call_id, status, valid, line for every message.

    messages: conv_id, turn, role, text, call_id, name, arguments (JSON), refs (array of call ids
    whose results the call refers to). A row with a name is a call, else one with a call_id is a
    result, else it is a message.
    """
    rows = messages.select(
        "conv_id", "turn", "role", "text", "call_id", "name", "arguments", "refs",
        F.when(F.col("name").isNotNull(), "call").when(F.col("call_id").isNotNull(), "result").otherwise("message").alias("kind"),
    )
    found = links(rows.filter("kind = 'call'"), rows.filter("kind = 'result'"))
    needs = rows.filter("kind = 'call' and call_id is not null").select("conv_id", "call_id", F.explode("refs").alias("needed")).filter("needed is not null")
    level = levels(needs, found)
    known = rows.filter("kind <> 'message' and call_id is not null").join(found, ["conv_id", "call_id"], "left").join(level, ["conv_id", "call_id"], "left")
    lone = rows.filter("kind = 'message' or call_id is null")
    for c, t in (("call_turn", "long"), ("result_turn", "long"), ("level", "int"), ("at", "long")):
        lone = lone.withColumn(c, F.lit(None).cast(t))
    asked = needs.select("conv_id", "call_id").distinct().withColumn("_asks", F.lit(True))
    every = known.join(asked, ["conv_id", "call_id"], "left").unionByName(lone.withColumn("_asks", F.lit(None).cast("boolean")))
    first = F.when(F.col("kind") == "call", F.col("call_turn")).when(F.col("kind") == "result", F.col("result_turn"))
    status = (
        F.when(F.col("kind") == "message", "message")
        .when(F.col("call_id").isNull(), "unnamed")
        .when(F.col("turn") != first, "repeated")
        .when(F.col("call_turn").isNull(), "orphan")
        .when(F.col("result_turn").isNull(), "unanswered")
        .when((F.col("kind") == "call") & F.col("_asks") & F.col("level").isNull(), "circular")
        .otherwise("linked")
    )
    # a result stands at or after its call, and a call at or after all it refers to; at one turn the level decides
    anchor = F.when(F.col("kind") == "result", F.greatest("at", "call_turn", "turn")).when(F.col("kind") == "call", F.greatest("at", "turn")).otherwise(F.col("turn"))
    line = F.when(
        F.col("kind") == "call",
        F.concat(F.lit('{"arguments":'), F.coalesce(canonical(F.col("arguments")), F.lit("null")), F.lit(',"id":'), _string("call_id"), F.lit(',"name":'), _string("name"), F.lit(',"role":'), _string("role"), F.lit("}")),
    ).otherwise(F.concat(F.lit('{"content":'), _string("text"), F.lit(',"id":'), _string("call_id"), F.lit(',"role":'), _string("role"), F.lit("}")))
    valid = F.when(F.col("kind") == "call", F.coalesce(valid_arguments(F.col("name"), F.col("arguments"), schemas), F.lit(False))).otherwise(True)
    out = every.select("conv_id", "turn", "kind", "call_id", status.alias("status"), valid.alias("valid"), line.alias("line"), anchor.alias("_at"), F.coalesce("level", F.lit(0)).alias("_level"), (F.col("kind") == "result").cast("int").alias("_after"))
    return placed(out, "conv_id", ["_at", "_level", "_after", "turn", "call_id", "line"]).drop("_at", "_level", "_after")


def _string(column: str) -> Column:
    """A JSON string, or null: Variant does the escaping."""
    return F.coalesce(F.to_json(F.to_variant_object(F.array(F.col(column)))).substr(F.lit(2), F.length(F.to_json(F.to_variant_object(F.array(F.col(column))))) - 2), F.lit("null"))


def turns_as_calls(conversations: DataFrame, tool: str = "reply") -> DataFrame:
    """Messages for format_calls from plain turns: a user's turn calls `tool`, the assistant's next turn is its result.

    References: exchange 1 and later ones refer to the one half as far, but each third from exchange 2 on refers
    to the one after it, so it has to move behind that one's result. There are no circles, and chains are
    as long as the logarithm of a conversation.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    n_words = F.when(F.trim(F.regexp_replace(text, r"\s+", " ")) == "", 0).otherwise(F.size(F.split(F.trim(F.regexp_replace(text, r"\s+", " ")), " ")))
    user, answer = F.col("role") == "user", F.col("role") == "assistant"
    asked = F.when(user, F.col("turn")).when(answer, F.col("turn") - 1)
    exchange = F.floor(F.col("turn") / 2)
    other = F.when(exchange % 3 == 2, exchange + 1).otherwise(F.floor(exchange / 2)) * 2 + F.col("turn") % 2
    refs = F.when(user & (exchange >= 1), F.array(F.concat(F.lit("c"), F.col("conv_id"), F.lit("-"), other.cast("long"))))
    return conversations.select(
        "conv_id", "turn", "role", "text",
        F.when(asked >= 0, F.concat(F.lit("c"), F.col("conv_id"), F.lit("-"), asked)).alias("call_id"),
        F.when(user, tool).alias("name"),
        F.when(user, F.to_json(F.struct(F.col("text").alias("prompt"), n_words.alias("words")))).alias("arguments"),
        F.coalesce(refs, F.array().cast("array<string>")).alias("refs"),
    )
