"""Tool-call linking in conversations, in DataFrame operations only.

Calls and results meet by a hash join on the call's identifier, with the results of an identifier aggregated first, so
repeated identifiers never multiply; null identifiers stay out of the join.  A conversation's calls are put in topological order of their dependencies, and in
message order (then by name, arguments and identifier) where these leave a choice: only calls between one and a later (or equal) turn it depends on are sorted in
rounds, the others stand in order already.  Missing dependencies and cycles are named in the status.
Numbers come from a range partitioning with counts carried over, so one conversation may be any part of the table.
Arguments are parsed to variants: their keys are sorted and their JSON is compact, which makes the canonical form.
"""

from __future__ import annotations

import json
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Stored, row_uid

#: name -> schema of its arguments, in the words of JSON Schema: type (one or a list), required, properties,
#: additionalProperties, enum, minimum, maximum, minLength, maxLength, items, minItems and maxItems.
SCHEMAS: dict[str, dict] = {
    name: {"type": "object", "properties": {"text": {"type": "string", "minLength": 1}, "turn": {"type": "integer", "minimum": 0}}, "required": ["text", "turn"], "additionalProperties": False}
    for name in ("reply", "configure")
}
ROWS_PER_PART = 50_000
#: What decides the order of calls of one turn.
CONTENT = ("name", "arguments", "call_id")
#: Tasks that the results of one identifier are dealt to.
SALTS = 16

_KINDS = {"string": ("STRING",), "integer": ("BIGINT",), "number": ("BIGINT", "DOUBLE", "DECIMAL"), "boolean": ("BOOLEAN",), "object": ("OBJECT",), "array": ("ARRAY",), "null": ("VOID",)}
_WORDS = frozenset("type required properties additionalProperties enum minimum maximum minLength maxLength items minItems maxItems".split())


def canonical(text: Column) -> Column:
    """Canonical JSON: compact, keys in order; null for text that is not JSON or repeats a key."""
    return F.to_json(F.try_parse_json(text))


def quoted(text: Column) -> Column:
    """A JSON string, or the JSON null."""
    inside = F.to_json(F.array(text))
    return F.when(text.isNull(), F.lit("null")).otherwise(F.substring(inside, F.lit(2), F.length(inside) - 2))


def fits(v: Column, schema: dict) -> Column:
    """Whether a variant fits a schema; nested objects and items of arrays are checked in the same expression."""
    if unknown := set(schema) - _WORDS:
        raise ValueError(f"unknown words in a schema: {sorted(unknown)}")
    found = F.regexp_extract(F.schema_of_variant(v), "^[A-Z]+", 0)
    kinds = [schema["type"]] if isinstance(schema.get("type"), str) else schema.get("type")
    ok = found.isin(*[k for kind in kinds for k in _KINDS[kind]]) if kinds else F.lit(True)
    if "enum" in schema:
        ok &= F.to_json(v).isin(*[json.dumps(e, separators=(",", ":"), sort_keys=True, ensure_ascii=False) for e in schema["enum"]])
    number = F.try_variant_get(v, "$", "double")
    for word, test in (("minimum", lambda x: number >= x), ("maximum", lambda x: number <= x)):
        if word in schema:
            ok &= ~found.isin(*_KINDS["number"]) | test(schema[word])
    length = F.length(F.try_variant_get(v, "$", "string"))
    for word, test in (("minLength", lambda x: length >= x), ("maxLength", lambda x: length <= x)):
        if word in schema:
            ok &= (found != "STRING") | test(schema[word])
    if {"items", "minItems", "maxItems"} & set(schema):
        items = F.try_variant_get(v, "$", "array<variant>")
        inside = F.size(items) >= schema.get("minItems", 0)
        if "maxItems" in schema:
            inside &= F.size(items) <= schema["maxItems"]
        if "items" in schema:
            inside &= F.forall(items, lambda x: F.coalesce(fits(x, schema["items"]), F.lit(False)))
        ok &= (found != "ARRAY") | inside
    if {"properties", "required", "additionalProperties"} & set(schema):
        fields, known = F.try_variant_get(v, "$", "map<string,variant>"), schema.get("properties", {})
        inside = F.lit(True)
        for field in schema.get("required", []):
            inside &= F.map_contains_key(fields, field)
        for field, own in known.items():
            inside &= ~F.map_contains_key(fields, field) | F.coalesce(fits(F.element_at(fields, F.lit(field)), own), F.lit(False))
        if schema.get("additionalProperties") is False:
            inside &= F.size(F.array_except(F.map_keys(fields), F.array(*[F.lit(f) for f in known]).cast("array<string>"))) == 0
        ok &= (found != "OBJECT") | inside
    return ok


def valid(name: Column, arguments: Column, schemas: dict[str, dict] = SCHEMAS) -> Column:
    """Whether the arguments (JSON) fit the schema of the call's name.  Unknown names, null or malformed arguments do not."""
    v = F.try_parse_json(arguments)
    out = F.lit(False)
    for known, schema in schemas.items():
        out = F.when(name == known, F.coalesce(fits(v, schema), F.lit(False))).otherwise(out)
    return F.coalesce(out, F.lit(False))


def ordered_positions(df: DataFrame, key: str, order: list[str], out: str, store: Stored, rows: int) -> DataFrame:
    """Number the rows of each key 0, 1, ... in the order of ``order`` (which must be total), whatever a key's size."""
    parts = max(8, -(-rows // ROWS_PER_PART))
    laid = store.put(df.repartitionByRange(parts, key, *order).withColumn("_pid", F.spark_partition_id()))
    before = Window.partitionBy(key).orderBy("_pid").rowsBetween(Window.unboundedPreceding, -1)
    offsets = laid.groupBy(key, "_pid").agg(F.count(F.lit(1)).alias("_n")).withColumn("_off", F.coalesce(F.sum("_n").over(before), F.lit(0))).select(F.col(key).alias("_k"), F.col("_pid").alias("_q"), "_off")
    inside = Window.partitionBy(key, "_pid").orderBy(*order)
    ranked = laid.withColumn("_r", F.row_number().over(inside))
    return ranked.join(offsets, (F.col(key).eqNullSafe(F.col("_k"))) & (F.col("_pid") == F.col("_q"))).withColumn(out, F.col("_off") + F.col("_r") - 1).drop("_k", "_q", "_off", "_r", "_pid")


def _tangled(keep: DataFrame, edges: DataFrame, store: Stored, rows: int) -> DataFrame:
    """The rows of ``keep`` between a call and one of no earlier turn that it depends on: a running maximum of how far
    the calls up to a turn reach, carried over the parts of a range partitioning."""
    back = edges.where("_d_at >= _at").groupBy("_uid").agg(F.max("_d_at").alias("_reach"))
    laid = store.put(keep.join(back, "_uid", "left").repartitionByRange(max(8, -(-rows // ROWS_PER_PART)), "conv_id", "_at").withColumn("_pid", F.spark_partition_id()))
    before = Window.partitionBy("conv_id").orderBy("_pid").rowsBetween(Window.unboundedPreceding, -1)
    carried = laid.groupBy("conv_id", "_pid").agg(F.max("_reach").alias("_n")).select(F.col("conv_id").alias("_k"), F.col("_pid").alias("_q"), F.max("_n").over(before).alias("_carried"))
    inside = Window.partitionBy("conv_id", "_pid").orderBy("_at").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    met = laid.withColumn("_in", F.max("_reach").over(inside)).join(carried, F.col("conv_id").eqNullSafe(F.col("_k")) & (F.col("_pid") == F.col("_q")))
    return store.put(met.where(F.greatest("_in", "_carried") >= F.col("_at")).select("_uid", "conv_id", "call_id", "_at"))


def _same_call(conv: str, call: str) -> Column:
    return F.col("conv_id").eqNullSafe(F.col(conv)) & (F.col("_dep") == F.col(call))


def _sorted_in_rounds(keep: DataFrame, edges: DataFrame, store: Stored, rows: int) -> tuple[DataFrame, DataFrame]:
    """(_uid, _t, _level) of the calls that a topological sort of the tangled ones places, _t being the turn after which
    they can stand, and (_uid) of those on a cycle.  A round places what waits for placed calls only, so there are as many
    rounds as the longest chain inside a tangle is long."""
    left = _tangled(keep, edges, store, rows)
    asked = store.put(edges.where("_d_at is not null").join(left.select("_uid"), "_uid", "left_semi").select("_uid", "conv_id", "_dep"))
    free = keep.where("call_id is not null").join(left.select("_uid"), "_uid", "left_anti")
    known = store.put(free.groupBy(F.col("conv_id").alias("_c"), F.col("call_id").alias("_d")).agg(F.min(F.struct(F.col("_at").alias("t"), F.lit(0).alias("level"))).alias("_key")))
    placed = []
    while True:
        met = asked.join(known, _same_call("_c", "_d"), "left").groupBy("_uid").agg(F.max("_key").alias("_last"), F.max(F.col("_key").isNull()).alias("_waits"))
        late = F.coalesce(F.col("_last.t") >= F.col("_at"), F.lit(False))
        ready = left.join(met, "_uid", "left").where(~F.coalesce("_waits", F.lit(False)))
        now = store.put(ready.select("_uid", "conv_id", "call_id", F.when(late, F.col("_last.t")).otherwise(F.col("_at")).alias("_t"), F.when(late, F.col("_last.level") + 1).otherwise(0).alias("_level")))
        if now.isEmpty():
            break
        placed.append(now.select("_uid", "_t", "_level"))
        left = store.put(left.join(now.select("_uid"), "_uid", "left_anti"))
        asked = store.put(asked.join(left.select("_uid"), "_uid", "left_semi"))
        fresh = now.where("call_id is not null").select(F.col("conv_id").alias("_c"), F.col("call_id").alias("_d"), F.struct(F.col("_t").alias("t"), F.col("_level").alias("level")).alias("_key"))
        known = store.put(known.unionByName(fresh).groupBy("_c", "_d").agg(F.min("_key").alias("_key")))
    cyclic, n = left, left.count()
    while n:  # calls that nothing left waits for are on no cycle
        needed = asked.join(cyclic.select("_uid"), "_uid", "left_semi").select(F.col("conv_id").alias("_c"), "_dep").distinct()
        cyclic = store.put(cyclic.join(needed, F.col("conv_id").eqNullSafe(F.col("_c")) & (F.col("call_id") == F.col("_dep")), "left_semi"))
        if (m := cyclic.count()) == n:
            break
        n = m
    none = keep.where("false").select("_uid", F.col("_at").alias("_t"), F.lit(0).alias("_level"))
    return reduce(DataFrame.unionByName, placed, none), cyclic.select("_uid")


def in_order(calls: DataFrame, store: Stored, rows: int) -> DataFrame:
    """Stored calls with a _uid, with their ``position`` in the conversation and ``_bad``: a dependency is missing in
    the conversation, or on a cycle with the call, or waits for a cycle and has no earlier place."""
    keep = calls.withColumn("_at", F.coalesce("turn", F.lit(-(2**63))))
    known = keep.where("call_id is not null").groupBy(F.col("conv_id").alias("_c"), F.col("call_id").alias("_d")).agg(F.min("_at").alias("_d_at"))
    edges = store.put(keep.select("_uid", "conv_id", "_at", F.explode("after").alias("_dep")).join(known, _same_call("_c", "_d"), "left").drop("_c", "_d"))
    if edges.where("_d_at >= _at").isEmpty():
        bad = edges.groupBy("_uid").agg(F.max(F.col("_d_at").isNull()).alias("_bad"))
        return ordered_positions(calls, "conv_id", ["turn", *CONTENT, "_uid"], "position", store, rows).join(bad, "_uid", "left")
    placed, cyclic = _sorted_in_rounds(keep, edges, store, rows)
    at = store.put(keep.join(placed, "_uid", "left").withColumns({"_t": F.coalesce("_t", "_at"), "_level": F.coalesce("_level", F.lit(0))}).drop("_at"))
    key = F.struct("_t", "_level")
    first = at.groupBy(F.col("conv_id").alias("_c"), F.col("call_id").alias("_d")).agg(F.min(key).alias("_key"))
    own = edges.select("_uid", "conv_id", "_dep").join(at.select("_uid", key.alias("_own")), "_uid")
    late = own.join(first, _same_call("_c", "_d"), "left").select("_uid", F.coalesce(F.col("_key") >= F.col("_own"), F.lit(True)).alias("_bad"))
    bad = late.unionByName(cyclic.withColumn("_bad", F.lit(True))).groupBy("_uid").agg(F.max("_bad").alias("_bad"))
    return ordered_positions(at, "conv_id", ["_t", "_level", "turn", *CONTENT, "_uid"], "position", store, rows).join(bad, "_uid", "left").drop("_t", "_level")


def link(calls: DataFrame, results: DataFrame, schemas: dict[str, dict] = SCHEMAS) -> DataFrame:
    """Calls with their results, in order, checked and serialised.

    calls: conv_id long, turn long, call_id string, name string, arguments string (JSON), after array<string> (call_ids
    it depends on).  results: call_id string, content string.  Other columns are not read.
    Returns for each call row: conv_id, position (from 0 in its conversation), call_id, name, n_results (results with its
    identifier), valid, status (``linked``, ``unanswered``, or ``bad_dependency`` if one is missing in the conversation or
    on a cycle) and record, the canonical JSON.  A call with several results takes the least content
    (``each_result`` gives them all).  Results of no call are given as
    rows with null position and name and status ``orphan``, one for each identifier.  Null identifiers link to nothing: such
    calls are unanswered, and each such result is an orphan of its own.  Calls of null conv_id are one conversation.  Repeated
    rows are calls (results) of their own.  Empty tables: empty result.
    """
    store = Stored(calls.sparkSession)
    keep = store.put(calls.select("conv_id", "turn", "call_id", "name", "arguments", "after").withColumn("_uid", row_uid()))
    rows = keep.count()
    answered = results.where("call_id is not null").groupBy("call_id").agg(F.count(F.lit(1)).alias("n_results"), F.min("content").alias("content"))
    placed = store.put(in_order(keep, store, rows))
    joined = placed.where("call_id is not null").join(answered.hint("shuffle_hash"), "call_id", "full")
    nameless = results.where("call_id is null").select("call_id", F.lit(1).cast("long").alias("n_results"), "content")
    joined = joined.unionByName(placed.where("call_id is null"), allowMissingColumns=True).unionByName(nameless, allowMissingColumns=True)
    is_call = F.col("_uid").isNotNull()
    n = F.coalesce("n_results", F.lit(0)).cast("long")
    fit = valid(F.col("name"), F.col("arguments"), schemas)
    status = F.when(~is_call, "orphan").when(F.coalesce("_bad", F.lit(False)), "bad_dependency").when(n == 0, "unanswered").otherwise("linked")
    record = F.concat(
        F.lit('{"after":'), F.to_json(F.coalesce("after", F.array().cast("array<string>"))),
        F.lit(',"arguments":'), F.coalesce(canonical(F.col("arguments")), F.lit("null")),
        F.lit(',"id":'), quoted(F.col("call_id")), F.lit(',"name":'), quoted(F.col("name")),
        F.lit(',"result":'), quoted(F.col("content")), F.lit(',"valid":'), fit.cast("string"), F.lit("}"),
    )
    return joined.select("conv_id", F.col("position").cast("long"), "call_id", "name", n.alias("n_results"), F.when(is_call, fit).alias("valid"), status.alias("status"), record.alias("record"))


def each_result(calls: DataFrame, results: DataFrame) -> DataFrame:
    """Every result row, beside the records of ``link``, which hold one result of a call.

    calls: conv_id, call_id.  results: conv_id long, turn long, call_id string, content string.  Returns for each result
    row: conv_id, turn, call_id, number (from 0 among the results of the identifier in the conversation, by turn), status
    (``answer``, or ``orphan`` without such a call in the conversation) and content.
    """
    store = Stored(results.sparkSession)
    rows = store.put(results.select("conv_id", "turn", "call_id", "content", F.struct("conv_id", "call_id").alias("_of")).withColumn("_uid", row_uid()))
    numbered = ordered_positions(rows, "_of", ["turn", "content", "_uid"], "number", store, rows.count()).withColumn("_salt", F.pmod("_uid", F.lit(SALTS)).cast("int"))
    asked = calls.select(F.col("conv_id").alias("_c"), F.col("call_id").alias("_d")).where("_d IS NOT NULL").distinct().withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    met = numbered.join(asked, F.col("conv_id").eqNullSafe(F.col("_c")) & (F.col("call_id") == F.col("_d")) & (F.col("_salt") == F.col("_s")), "left")
    return met.select("conv_id", "turn", "call_id", F.col("number").cast("long"), F.when(F.col("_d").isNull(), "orphan").otherwise("answer").alias("status"), "content")


def calls_and_results(conversations: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The calls and results that plain conversations hold.

    A user turn calls ``reply`` and a system turn ``configure``, with the text and the turn as arguments, under the
    identifier conv_id:turn; a user turn after turn 1 depends on the call two turns before.  Any other turn is a result for
    the call one turn before.  Null roles are results; with a null conv_id or turn there is no identifier.
    """
    name = lambda shift: F.concat(F.col("conv_id").cast("string"), F.lit(":"), (F.col("turn") - shift).cast("string"))
    asks = F.coalesce(F.col("role").isin("user", "system"), F.lit(False))
    arguments = F.concat(F.lit('{"turn":'), F.coalesce(F.col("turn").cast("string"), F.lit("null")), F.lit(',"text":'), quoted(F.col("text")), F.lit("}"))
    calls = conversations.where(asks).select(
        "conv_id", "turn", name(0).alias("call_id"), F.when(F.col("role") == "user", "reply").otherwise("configure").alias("name"), arguments.alias("arguments"),
        F.when((F.col("role") == "user") & (F.col("turn") > 1), F.array(name(2))).otherwise(F.array().cast("array<string>")).alias("after"),
    )
    return calls, conversations.where(~asks).select("conv_id", "turn", name(1).alias("call_id"), F.col("text").alias("content"))


def link_conversations(conversations: DataFrame) -> DataFrame:
    return link(*calls_and_results(conversations))


def conversation_results(conversations: DataFrame) -> DataFrame:
    return each_result(*calls_and_results(conversations))


#: The same rows in DuckDB SQL.
ORACLE = """
WITH m AS (SELECT conv_id, turn, role, text,
                  coalesce(role IN ('user', 'system'), false) AS asks,
                  CAST(conv_id AS VARCHAR) || ':' || CAST(turn AS VARCHAR) AS own,
                  CAST(conv_id AS VARCHAR) || ':' || CAST(turn - 1 AS VARCHAR) AS one,
                  CAST(conv_id AS VARCHAR) || ':' || CAST(turn - 2 AS VARCHAR) AS two
           FROM conversations),
c AS (SELECT conv_id, turn, own AS call_id, CASE role WHEN 'user' THEN 'reply' ELSE 'configure' END AS name, text,
             role = 'user' AND turn > 1 AS waits, CASE WHEN role = 'user' AND turn > 1 THEN two END AS dep,
             row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, CASE role WHEN 'user' THEN 'reply' ELSE 'configure' END,
                                                              coalesce(CAST(to_json(text) AS VARCHAR), 'null')) - 1 AS position,
             coalesce(length(text), 0) >= 1 AND turn IS NOT NULL AND coalesce(turn, 0) >= 0 AS fits
      FROM m WHERE asks),
k AS (SELECT call_id, min(turn) AS t FROM c GROUP BY call_id),
r AS (SELECT one AS call_id, count(*) AS n, min(text) AS content FROM m WHERE NOT asks AND one IS NOT NULL GROUP BY one
      UNION ALL SELECT NULL, 1, text FROM m WHERE NOT asks AND one IS NULL)
SELECT c.conv_id, c.position AS position, coalesce(c.call_id, r.call_id) AS call_id, c.name AS name,
       coalesce(r.n, 0) AS n_results, c.fits AS valid,
       CASE WHEN c.name IS NULL THEN 'orphan'
            WHEN c.waits AND coalesce(NOT (k.t < c.turn), true) THEN 'bad_dependency'
            WHEN r.n IS NULL THEN 'unanswered' ELSE 'linked' END AS status,
       CASE WHEN c.name IS NULL
            THEN '{"after":[],"arguments":null,"id":' || coalesce(CAST(to_json(r.call_id) AS VARCHAR), 'null') || ',"name":null,"result":' || coalesce(CAST(to_json(r.content) AS VARCHAR), 'null') || ',"valid":false}'
            ELSE '{"after":' || CASE WHEN coalesce(c.waits, false) THEN '[' || coalesce(CAST(to_json(c.dep) AS VARCHAR), 'null') || ']' ELSE '[]' END
                 || ',"arguments":{"text":' || coalesce(CAST(to_json(c.text) AS VARCHAR), 'null') || ',"turn":' || coalesce(CAST(c.turn AS VARCHAR), 'null')
                 || '},"id":' || coalesce(CAST(to_json(c.call_id) AS VARCHAR), 'null') || ',"name":' || to_json(c.name)
                 || ',"result":' || coalesce(CAST(to_json(r.content) AS VARCHAR), 'null')
                 || ',"valid":' || CASE WHEN c.fits THEN 'true' ELSE 'false' END || '}' END AS record
FROM c FULL JOIN r ON c.call_id = r.call_id LEFT JOIN k ON k.call_id = c.dep
"""
