"""Tool-call linking, in DataFrame operations only.

Calls and results are hash-joined by their identifier. A call comes after the calls whose results its arguments refer to
("$ref:<id>"); levels of that order are found by rounds of joins that raise a call above what it refers to, so ordering
by (level, turn, id) is a topological order of a conversation. Arguments are checked against the tool's schema, and
each linked pair becomes one canonical JSON text: keys sorted, no blanks.

Identifiers spread rows, so a conversation that holds a third of all rows is not gathered anywhere; levels travel along
references only.

Defined cases: a call without a result has linked = false and no result; a result without a call has its own row with null
name; null identifiers link with nothing; several results of one call all stay; arguments that are no JSON object are
invalid and serialised as null; a reference to nothing that is known counts as none; calls in a cycle of references
get level null.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathweave.llm import common as C

#: Required arguments of each tool and their types; a stated parameter.
SCHEMAS = {"reply": {"text": "string", "words": "integer"}}
#: Chains of up to 2**24 calls; pointers that have not ended then go round a cycle.
DOUBLINGS = 24
_TYPES = {"string": "STRING", "integer": "BIGINT", "number": "DECIMAL|DOUBLE|FLOAT|BIGINT", "boolean": "BOOLEAN", "object": "OBJECT", "array": "ARRAY"}


def canonical(json: Column) -> Column:
    """The JSON text with sorted keys and without blanks; null where it isn't JSON."""
    return F.to_json(F.try_parse_json(json))


def valid(name: Column, arguments: Column, schemas=SCHEMAS) -> Column:
    """Whether the arguments hold all that the tool's schema requires, of the right types; unknown tools are invalid."""
    v = F.try_parse_json(arguments)
    ok = F.lit(False)
    for tool, fields in schemas.items():
        fits = F.coalesce(F.startswith(F.schema_of_variant(v), F.lit("OBJECT")), F.lit(False))
        for field, kind in fields.items():
            part = F.try_variant_get(v, f"$.{field}", "variant")
            fits = fits & F.coalesce(F.rlike(F.schema_of_variant(part), F.lit(f"^({_TYPES[kind]})")), F.lit(False))
        ok = F.when(name == tool, fits).otherwise(ok)
    return ok


def levels(calls: DataFrame) -> DataFrame:
    """calls(id, refs array<string>) -> id, level: 0 without known references, else one above the highest."""
    calls = calls.filter("id is not null").select("id", "refs")
    nodes = C.settle(calls.select("id").distinct(), "tools-nodes")
    edges = calls.select("id", F.explode("refs").alias("ref")).distinct().join(nodes.select(F.col("id").alias("ref")), "ref", "left_semi")
    edges = C.settle(edges, "tools-edges")
    if edges.groupBy("id").count().filter("count > 1").limit(1).count() == 0:
        return _chain_levels(nodes, edges)
    level = nodes.join(edges.select("id").distinct(), "id", "left_anti").select("id", F.lit(0).cast("long").alias("level"))
    done, left = level, edges
    while True:
        # Calls all of whose references have a level.
        known = C.settle(left.join(done.withColumnRenamed("id", "ref"), "ref", "left"), "tools-known")
        ready = known.groupBy("id").agg(F.max("level").alias("top"), F.count(F.lit(1)).alias("n"), F.count("level").alias("have")).filter("n = have").select("id", (F.col("top") + 1).alias("level"))
        ready = C.settle(ready, "tools-ready")
        if ready.limit(1).count() == 0:
            break
        done = C.settle(done.union(ready), "tools-done")
        left = C.settle(left.join(ready.select("id"), "id", "left_anti"), "tools-left")
    return done


def _chain_levels(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """Levels where each call refers to one other at most: distances to the chain's first call by pointer doubling, in a number
    of rounds that is the logarithm of the longest chain. Calls that still point somewhere after DOUBLINGS rounds are in or behind a cycle."""
    at = nodes.select("id").join(edges, "id", "left").select("id", F.col("ref").alias("up"), F.when(F.col("ref").isNull(), 0).otherwise(1).cast("long").alias("level"))
    at = C.settle(at, "tools-chain")
    rounds = 0
    while rounds < DOUBLINGS and at.filter("up is not null").limit(1).count():
        far = at.select(F.col("id").alias("up"), F.col("up").alias("next"), F.col("level").alias("more"))
        at = C.settle(at.join(far, "up", "left").select("id", F.col("next").alias("up"), (F.col("level") + F.coalesce("more", F.lit(0))).alias("level")), "tools-chain")
        rounds += 1
    return at.filter("up is null").select("id", "level")


def linked(calls: DataFrame, results: DataFrame, schemas=SCHEMAS) -> DataFrame:
    """calls(id, conv_id, turn, name, arguments, refs), results(id, conv_id, turn, content) -> a row for each pair, each call
    without a result and each result without a call: conv_id, call_id, turn, result_turn, name, level, valid, linked, json."""
    calls = calls.select("id", "conv_id", "turn", "name", "arguments", "refs")
    placed = calls.join(levels(calls.select("id", "refs")), "id", "left").withColumn("level", F.when(F.col("id").isNull(), F.lit(0).cast("long")).otherwise(F.col("level")))
    r = results.select(F.col("id").alias("r_id"), F.col("conv_id").alias("r_conv"), F.col("turn").alias("r_turn"), F.col("content"))
    pairs = placed.join(r, placed["id"] == r["r_id"], "left")
    args = F.to_json(F.try_parse_json("arguments"))
    body = F.concat(
        F.lit('{"arguments":'), F.coalesce(args, F.lit("null")), F.lit(',"id":'), _quoted(F.col("id")), F.lit(',"name":'), _quoted(F.col("name")),
        F.lit(',"result":'), F.when(F.col("r_id").isNull(), F.lit("null")).otherwise(_quoted(F.col("content"))), F.lit("}"),
    )
    own = pairs.select("conv_id", F.col("id").alias("call_id"), "turn", F.col("r_turn").alias("result_turn"), "name", "level", valid(F.col("name"), F.col("arguments"), schemas).alias("valid"), F.col("r_id").isNotNull().alias("linked"), body.alias("json"))
    lone = r.join(placed.select(F.col("id").alias("r_id")).distinct(), "r_id", "left_anti")
    lone = lone.select(F.col("r_conv").alias("conv_id"), F.col("r_id").alias("call_id"), F.lit(None).cast("long").alias("turn"), F.col("r_turn").alias("result_turn"), F.lit(None).cast("string").alias("name"), F.lit(None).cast("long").alias("level"), F.lit(False).alias("valid"), F.lit(False).alias("linked"), F.lit(None).cast("string").alias("json"))
    return own.unionByName(lone)


def _quoted(c: Column) -> Column:
    """A JSON string, or null."""
    array = F.to_json(F.array(c))
    return F.coalesce(F.when(c.isNotNull(), F.substring(array, F.lit(2), F.length(array) - 2)), F.lit("null"))


def from_messages(messages: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Calls and results in messages(conv_id, turn, role, text): an assistant's text {"tool_calls": [{id, name, arguments}]}
    and a tool's text {"tool_call_id", "content"}."""
    shape = "struct<tool_calls: array<struct<id: string, name: string, arguments: string>>>"
    calls = messages.filter("role = 'assistant'").select("conv_id", "turn", F.explode(F.from_json("text", shape)["tool_calls"]).alias("c"))
    calls = calls.select(F.col("c.id").alias("id"), "conv_id", "turn", F.col("c.name").alias("name"), F.col("c.arguments").alias("arguments"), refs_of(F.col("c.arguments")).alias("refs"))
    results = messages.filter("role = 'tool'").select(F.get_json_object("text", "$.tool_call_id").alias("id"), "conv_id", "turn", F.get_json_object("text", "$.content").alias("content"))
    return calls, results


def refs_of(arguments: Column) -> Column:
    return F.coalesce(F.regexp_extract_all(arguments, F.lit(r"\$ref:([A-Za-z0-9_:.-]+)"), F.lit(1)), F.array().cast("array<string>"))


def from_dialogue(messages: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Dialogues without tool messages, read as calls of one tool: each user's turn calls "reply" with its text, the
    assistant's next turn is the result, and a call refers to the call two turns earlier."""
    m = messages.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", F.col("text").cast("string").alias("text"))
    key = lambda d: F.concat_ws(":", F.when(F.col("conv_id").isNotNull() & F.col("turn").isNotNull(), F.col("conv_id").cast("string")), (F.col("turn") - d).cast("string"))
    known = F.col("conv_id").isNotNull() & F.col("turn").isNotNull()
    words = F.size(F.array_remove(F.split(F.coalesce("text", F.lit("")), r"[\x20\x09-\x0D]+"), ""))
    arguments = F.to_json(F.struct("text", words.alias("words")))
    calls = m.filter("role = 'user'").select(F.when(known, key(0)).alias("id"), "conv_id", "turn", F.lit("reply").alias("name"), arguments.alias("arguments"), F.when(known, F.array(key(2))).otherwise(F.array().cast("array<string>")).alias("refs"))
    results = m.filter("role = 'assistant'").select(F.when(known, key(1)).alias("id"), "conv_id", "turn", F.col("text").alias("content"))
    return calls, results
