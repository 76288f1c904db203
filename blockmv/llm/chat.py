"""Tool calls of conversations: linked to their results, ordered, validated and written as canonical JSON.

All of it is DataFrame functions. Calls and results meet in a hash join on the identifier. What a call waits for is a
graph: any number of other calls. Its depth is the longest way up to a call that waits for none, so sorting by depth is a
topological order. Chains, calls that wait for one other each, are jumped over by pointer doubling: after k rounds a call
knows its ancestor 2**k steps up, so a chain of n calls needs log2(n) joins. Calls that wait for several are then peeled
level by level, in as many joins as such calls follow on one another. Calls are numbered inside their thread by a
range-partitioned sort, whose partitions count their rows: no thread has to fit a task.

Arguments are parsed as variants, whose objects keep their keys sorted, so writing them back is canonical; they are
validated against a schema per tool: nested fields, types of items, allowed values, least and greatest numbers.

Defined results (column ``status``): linked; no_result (a call without result); no_call (a result whose identifier no
call has); repeated_call (a further call of an identifier: results link to its first call, by position, tool and
arguments, and what any of them waits for counts). Calls in or below a cycle have a null depth and a null ordinal.
Identifiers that no call has are not waited for. Arguments that are null, not JSON, or not an object are invalid and
have null canonical arguments. Null identifiers never match, wait for nothing and come last at their place. Empty tables
give no rows.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common


@dataclass(frozen=True)
class Field:
    """kinds: prefixes of the variant's type names, such as STRING, BIGINT, DECIMAL, BOOLEAN, ARRAY, OBJECT.

    fields: those of an object (None: any), items: what each item of an array must be, one_of: the allowed values,
    least and most: bounds of a number. Objects have no other fields than these unless they are ``open_``.
    """

    name: str
    kinds: tuple[str, ...]
    required: bool = True
    fields: tuple[Field, ...] | None = None
    items: Field | None = None
    one_of: tuple | None = None
    least: float | None = None
    most: float | None = None
    open_: bool = False


Schemas = dict[str, tuple[Field, ...]]


def _fits(value: Column, field: Field) -> Column:
    """Whether a variant, which is there, is what the field asks for."""
    kind = F.schema_of_variant(value)
    out = F.lit(False)
    for k in field.kinds:
        out = out | kind.startswith(k)
    if field.one_of is not None:
        out = out & F.to_json(value).isin([json.dumps(v, ensure_ascii=False, separators=(",", ":"), sort_keys=True) for v in field.one_of])
    number = F.try_variant_get(value, "$", "double")
    if field.least is not None:
        out = out & F.coalesce(number >= field.least, F.lit(False))
    if field.most is not None:
        out = out & F.coalesce(number <= field.most, F.lit(False))
    if field.fields is not None:
        out = out & (~kind.startswith("OBJECT") | _object_fits(value, field.fields, field.open_))
    if field.items is not None:
        each = F.forall(F.try_variant_get(value, "$", "array<variant>"), lambda x: F.coalesce(_fits(x, field.items), F.lit(False)))
        out = out & (~kind.startswith("ARRAY") | F.coalesce(each, F.lit(False)))
    return out


def _object_fits(value: Column, fields: tuple[Field, ...], open_: bool = False) -> Column:
    out = F.lit(True)
    if not open_:
        known = F.array(*[F.lit(f.name) for f in fields]).cast("array<string>")
        out = F.size(F.array_except(F.json_object_keys(F.to_json(value)), known)) == 0
    for f in fields:
        part = F.try_variant_get(value, "$['" + f.name + "']", "variant")
        out = out & F.when(part.isNull(), F.lit(not f.required)).otherwise(F.coalesce(_fits(part, f), F.lit(False)))
    return out


def arguments_valid(tool: Column, parsed: Column, schemas: Schemas) -> Column:
    """Whether parsed arguments (variant) are an object that the tool's schema allows; false for unknown tools."""
    out = F.lit(False)
    is_object = F.schema_of_variant(parsed).startswith("OBJECT")
    for name, fields in schemas.items():
        out = F.when(tool == name, F.coalesce(is_object & _object_fits(parsed, fields), F.lit(False))).otherwise(out)
    return F.coalesce(out, F.lit(False))


def canonical(parsed: Column) -> Column:
    """Keys sorted, no white space, numbers in shortest form: null unless an object."""
    return F.when(F.schema_of_variant(parsed).startswith("OBJECT"), F.to_json(parsed))


def _chains(waits: DataFrame, ids: DataFrame) -> DataFrame:
    """waits (child, parent), ids (call_id) -> call_id, top, steps: the nearest call upwards, or itself, that waits for
    none or for several, and how far up it is; top is null below a cycle of chains."""
    ups = waits.groupBy("child").agg(F.count("*").alias("ways"), F.min("parent").alias("parent"))
    met = ids.join(ups, ids["call_id"] == ups["child"], "left")
    single = F.coalesce(F.col("ways") == 1, F.lit(False))
    now = met.select("call_id", F.when(single, F.col("parent")).otherwise(F.col("call_id")).alias("top"), single.cast("long").alias("steps"))
    # open: top is known to wait for a single call itself
    chained = met.filter(single).select(F.col("call_id").alias("k"))
    now = now.join(chained, now["top"] == chained["k"], "left").select("call_id", "top", "steps", F.col("k").isNotNull().alias("open"))
    now = common.materialise(now, "chains")
    left = now.filter("open").count()
    while left:
        above = now.select(F.col("call_id").alias("k"), F.col("top").alias("next"), F.col("steps").alias("more"), F.col("open").alias("still"))
        met = now.filter("open").join(above, F.col("top") == F.col("k"))
        moved = met.select("call_id", F.col("next").alias("top"), (F.col("steps") + F.col("more")).alias("steps"), F.col("still").alias("open"))
        after = common.materialise(now.filter("not open").union(moved), "chains")
        common.discard(now)
        # every round closes some chain as long as any ends; cycles never do
        now, before, left = after, left, after.filter("open").count()
        if left == before:
            break
    return now.select("call_id", F.when(~F.col("open"), F.col("top")).alias("top"), "steps")


def depths(waits: DataFrame, ids: DataFrame) -> DataFrame:
    """waits (child, parent), ids (call_id), both distinct -> call_id, depth: the longest way up; null below a cycle."""
    waits = common.materialise(waits.join(ids.select(F.col("call_id").alias("parent")), "parent", "left_semi"), "waits")
    chains = common.materialise(_chains(waits, ids), "tops")
    several = waits.groupBy("child").count().filter("count > 1").select("child")
    ends = chains.select(F.col("call_id").alias("parent"), "top", "steps")
    open_ = waits.join(several, "child").join(ends, "parent").select("child", "top", (F.col("steps") + 1).alias("steps"))
    roots = chains.filter("call_id = top").join(several, chains["call_id"] == several["child"], "left_anti")
    done = common.materialise(roots.select(F.col("call_id").alias("node"), F.lit(0).cast("long").alias("depth")), "levels")
    open_ = common.materialise(open_, "open")
    while not open_.isEmpty():
        met = open_.join(done, open_["top"] == done["node"], "left")
        ready = met.groupBy("child").agg(F.count_if(F.col("node").isNull()).alias("missing"), F.max(F.col("depth") + F.col("steps")).alias("depth"))
        level = common.materialise(ready.filter("missing = 0").select(F.col("child").alias("node"), "depth"), "level")
        if level.isEmpty():
            break
        now = common.materialise(done.union(level), "levels")
        rest = common.materialise(open_.join(level, open_["child"] == level["node"], "left_anti"), "open")
        for old in (done, open_, level):
            common.discard(old)
        done, open_ = now, rest
    met = chains.join(done, chains["top"] == done["node"], "left")
    return met.select("call_id", (F.col("depth") + F.col("steps")).alias("depth"))


def _ranked(rows: DataFrame, thread: str, order: list[Column], name: str) -> DataFrame:
    """rows with ``name``: their place inside the thread, from 0. Partitions are ranges of (thread, order) and count
    their rows, so a thread may go over any number of tasks."""
    keys = [F.col(thread).asc_nulls_first(), *order]
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = rows.repartitionByRange(parts, *keys).sortWithinPartitions(*keys).withColumn("_place", F.monotonically_increasing_id())
    placed = common.materialise(placed, "ordered")
    # the low 33 bits of the id count the rows of a partition
    part, at = F.shiftright("_place", 33), F.col("_place").bitwiseAND(F.lit((1 << 33) - 1))
    placed = placed.select("*", part.alias("_part"), at.alias("_at"))
    sizes = placed.groupBy("_part").count().collect()  # one row per partition
    total, firsts = 0, []
    for r in sorted(sizes):
        firsts.append((r["_part"], total))
        total += r["count"]
    known = F.broadcast(rows.sparkSession.createDataFrame(firsts, "_p long, _before long"))
    ranked = placed.join(known, placed["_part"] == known["_p"]).withColumn("_rank", F.col("_before") + F.col("_at"))
    low = ranked.groupBy(F.col(thread).alias("_t")).agg(F.min("_rank").alias("_low"))
    met = ranked.join(low, ranked[thread].eqNullSafe(low["_t"]))
    return met.select(*rows.columns, (F.col("_rank") - F.col("_low")).alias(name))


def link_tool_calls(calls: DataFrame, results: DataFrame, schemas: Schemas) -> DataFrame:
    """calls (call_id, tool, arguments, after, position[, thread]), results (call_id, content, position), positions
    comparable -> one row per call without result, per result, and per further call of an identifier: call_id, status,
    tool, call_position, result_position, depth, ordinal, arguments_valid, message (canonical JSON of call and result).

    ``after``: the identifier, or an array of identifiers, of what the call waits for. ``ordinal``: the call's place in
    the topological order of its thread, from 0: by depth, then position, identifier, tool and arguments.
    """
    waits = F.col("after") if dict(calls.dtypes)["after"].startswith("array") else F.array("after")
    thread = F.col("thread") if "thread" in calls.columns else F.lit(None).cast("string")
    own = calls.select("call_id", "tool", "arguments", waits.alias("after"), "position", thread.alias("thread"), F.monotonically_increasing_id().alias("row"))
    own = common.materialise(own, "calls")
    named = own.filter("call_id is not null")
    best = F.struct(F.col("position").isNull(), "position", F.col("tool").isNull(), "tool", F.col("arguments").isNull(), "arguments", "row")
    per_id = common.materialise(named.groupBy("call_id").agg(F.min(best)["row"].alias("first")), "identifiers")
    links = named.select(F.col("call_id").alias("child"), F.explode("after").alias("parent")).filter("parent is not null").distinct()
    depth = depths(links, per_id.select("call_id")).withColumnRenamed("call_id", "d_id")
    c = own.join(per_id.select(F.col("call_id").alias("p_id"), "first"), F.col("call_id") == F.col("p_id"), "left")
    c = c.join(depth, F.col("call_id") == F.col("d_id"), "left")
    # a call without identifier waits for nothing
    deep = F.when(F.col("call_id").isNull(), F.lit(0).cast("long")).otherwise(F.col("depth"))
    c = c.select(*own.drop("after").columns, deep.alias("depth"), (F.col("row") == F.coalesce("first", "row")).alias("is_first"))
    order = [F.col("depth").asc(), *[F.col(k).asc_nulls_last() for k in ("position", "call_id", "tool", "arguments")]]
    sorted_ = _ranked(c.filter("depth is not null"), "thread", order, "ordinal")
    cyclic = c.filter("depth is null").withColumn("ordinal", F.lit(None).cast("long"))
    parsed = sorted_.unionByName(cyclic).withColumn("parsed", F.try_parse_json("arguments"))
    c = parsed.select(
        F.col("call_id").alias("c_id"),
        "tool",
        F.col("position").alias("call_position"),
        "depth",
        "ordinal",
        "is_first",
        arguments_valid(F.col("tool"), F.col("parsed"), schemas).alias("arguments_valid"),
        canonical(F.col("parsed")).alias("canonical"),
    )
    c = common.materialise(c, "linked-calls")
    r = results.select(F.col("call_id").alias("r_id"), "content", F.col("position").alias("result_position"))
    firsts = c.filter("is_first and c_id is not null")
    met = r.join(firsts.hint("shuffle_hash"), r["r_id"] == firsts["c_id"], "left")
    met = met.withColumn("status", F.when(F.col("c_id").isNull(), "no_call").otherwise("linked"))
    answered = r.select(F.col("r_id").alias("a_id")).distinct()
    rest = c.filter("is_first").join(answered, F.col("c_id") == F.col("a_id"), "left_anti").withColumn("status", F.lit("no_result"))
    rest = rest.unionByName(c.filter("not is_first").withColumn("status", F.lit("repeated_call")))
    both = met.unionByName(rest, allowMissingColumns=True)
    text = F.concat(
        F.lit('{"arguments":'),
        F.coalesce("canonical", F.lit("null")),
        F.lit(',"id":'),
        F.coalesce(_quoted(F.coalesce("c_id", "r_id")), F.lit("null")),
        F.lit(',"result":'),
        F.coalesce(_quoted(F.col("content")), F.lit("null")),
        F.lit(',"tool":'),
        F.coalesce(_quoted(F.col("tool")), F.lit("null")),
        F.lit("}"),
    )
    return both.select(
        F.coalesce("c_id", "r_id").alias("call_id"),
        "status",
        "tool",
        "call_position",
        "result_position",
        "depth",
        "ordinal",
        "arguments_valid",
        text.alias("message"),
    )


def _quoted(text: Column) -> Column:
    """A string as JSON, by the same writer as the arguments."""
    return F.to_json(F.to_variant_object(F.array(text))).substr(F.lit(2), F.length(F.to_json(F.to_variant_object(F.array(text)))) - 2)


#: Tools of the conversations query: what a user's turn asks for, and what a system turn sets.
CONVERSATION_TOOLS: Schemas = {
    "ask": (Field("prompt", ("STRING",)), Field("turn", ("BIGINT",)), Field("conversation", ("BIGINT",))),
    "configure": (Field("instructions", ("STRING",)), Field("turn", ("BIGINT",))),
}


def conversation_calls(turns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Turns as calls and results: a user's or system turn calls a tool, a turn of any other role answers the turn before.

    A call waits for the one two turns before, and for the one before if that is a system turn's, so depth follows the
    dialogue.
    """
    key = lambda turn: F.concat(F.lit("c"), F.col("conv_id"), F.lit("-"), turn)
    user = F.struct(F.col("text").alias("prompt"), F.col("turn"), F.col("conv_id").alias("conversation"))
    system = F.struct(F.col("turn"), F.col("text").alias("instructions"))
    is_call = F.coalesce(F.col("role").isin("user", "system"), F.lit(False))
    asked = turns.filter(is_call)
    heads = turns.filter("role = 'system'").select(key(F.col("turn")).alias("s_id")).distinct()
    asked = asked.join(heads, key(F.col("turn") - 1) == F.col("s_id"), "left")
    calls = asked.select(
        key(F.col("turn")).alias("call_id"),
        F.when(F.col("role") == "user", "ask").otherwise("configure").alias("tool"),
        F.when(F.col("role") == "user", F.to_json(user)).otherwise(F.to_json(system)).alias("arguments"),
        F.array("s_id", key(F.col("turn") - 2)).alias("after"),
        F.col("turn").alias("position"),
        F.col("conv_id").cast("string").alias("thread"),
    )
    answered = turns.filter(~is_call)
    results = answered.select(key(F.col("turn") - 1).alias("call_id"), F.col("text").alias("content"), F.col("turn").alias("position"))
    return calls, results


def link_conversations(turns: DataFrame) -> DataFrame:
    """conversations (conv_id, turn, role, text) -> the rows of ``link_tool_calls`` with md5 of the message."""
    calls, results = conversation_calls(turns)
    linked = link_tool_calls(calls, results, CONVERSATION_TOOLS)
    return linked.withColumn("message_md5", F.md5("message"))
