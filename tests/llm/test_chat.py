import json

import duckdb
import pytest
from helpers import SMALL, TINY, duck, rows_of_duck, rows_of_spark
from pyspark.sql import functions as F

from hypertriad.llm import chat

SCHEMAS = {
    "add": {"type": "object", "required": ["a"], "additionalProperties": False, "properties": {"a": {"type": "integer"}, "b": {"type": "number"}, "tag": {"type": "string", "minLength": 2}, "on": {"type": "boolean"}, "xs": {"type": "array"}, "o": {"type": "object"}}},
    "book": {
        "type": "object", "required": ["who", "seats"],
        "properties": {
            "who": {"type": "object", "required": ["name"], "properties": {"name": {"type": "string", "minLength": 1, "maxLength": 5}, "age": {"type": ["integer", "null"], "minimum": 18}}, "additionalProperties": False},
            "seats": {"type": "array", "minItems": 1, "maxItems": 3, "items": {"type": "integer", "minimum": 1, "maximum": 9}},
            "class": {"enum": ["first", "second", 3]}, "grid": {"type": "array", "items": {"type": "array", "items": {"type": "number"}}},
        },
    },
}
CALLS = "conv_id long, turn long, call_id string, name string, arguments string, after array<string>"


def test_same_rows_as_sql(spark):
    for d in (TINY, SMALL):
        assert rows_of_spark(chat.link_conversations(spark.read.parquet(f"{d}/conversations.parquet"))) == rows_of_duck(duck(d), chat.ORACLE)


def test_native(spark):
    plan = chat.link_conversations(spark.read.parquet(f"{TINY}/conversations.parquet"))._jdf.queryExecution().toString()
    assert not any(w in plan for w in ("Python", "Pandas", "Arrow"))


def test_validation(spark):
    cases = {'{"a": 1}': True, '{"a": 1, "b": 2.5}': True, '{"a": "1"}': False, '{"b": 1}': False, '{"a": 1, "c": 1}': False, '{"a": 1, "tag": "x"}': False, '{"a": 1, "tag": "xy"}': True, '{"a": 1, "on": true, "xs": [1], "o": {}}': True, '{"a": 1, "xs": 3}': False, "not json": False, "[1]": False, '{"a": null}': False, None: False}
    df = spark.createDataFrame([(k,) for k in cases], "j string")
    got = df.select("j", chat.valid(F.lit("add"), F.col("j"), SCHEMAS).alias("ok"), chat.valid(F.lit("other"), F.col("j"), SCHEMAS).alias("no")).collect()
    assert {r["j"]: r["ok"] for r in got} == cases and not any(r["no"] for r in got)


def test_nested_schemas(spark):
    good = '{"who": {"name": "Ann"}, "seats": [1, 9]}'
    cases = {
        good: True, '{"who": {"name": "Ann", "age": 18}, "seats": [2], "class": "first", "more": 1}': True, '{"who": {"name": "Ann", "age": null}, "seats": [2], "class": 3}': True,
        '{"who": {"name": "Ann", "age": 17}, "seats": [2]}': False, '{"who": {"name": ""}, "seats": [2]}': False, '{"who": {"name": "Annabel"}, "seats": [2]}': False, '{"who": {}, "seats": [2]}': False,
        '{"who": {"name": "Ann", "x": 1}, "seats": [2]}': False, '{"who": "Ann", "seats": [2]}': False, '{"who": {"name": "Ann"}, "seats": []}': False, '{"who": {"name": "Ann"}, "seats": [1, 2, 3, 4]}': False,
        '{"who": {"name": "Ann"}, "seats": [0]}': False, '{"who": {"name": "Ann"}, "seats": [10]}': False, '{"who": {"name": "Ann"}, "seats": ["1"]}': False, '{"who": {"name": "Ann"}, "seats": [1], "class": "third"}': False,
        '{"who": {"name": "Ann"}, "seats": [1], "grid": [[1, 2.5], []]}': True, '{"who": {"name": "Ann"}, "seats": [1], "grid": [[1], ["x"]]}': False, '{"who": {"name": "Ann"}, "seats": null}': False, "[]": False,
    }
    df = spark.createDataFrame([(k,) for k in cases], "j string")
    got = {r["j"]: r["ok"] for r in df.select("j", chat.valid(F.lit("book"), F.col("j"), SCHEMAS).alias("ok")).collect()}
    assert got == cases
    with pytest.raises(ValueError):
        chat.fits(F.col("j"), {"pattern": "x"})


def test_nulls_and_ties_as_in_sql(spark, tmp_path):
    rows = [(1, 0, "user", "b"), (1, 0, "user", "a"), (1, 0, "system", "c"), (1, 0, "user", 'a"q'), (1, 0, "user", None), (1, 1, "assistant", "y"), (1, 1, None, "x"), (1, None, "user", "n"), (1, None, "tool", "n"), (1, 2, "user", "z"), (1, 2, "user", "z"), (1, 7, "user", "gone")]
    rows += [(None, 0, "user", "p"), (None, 1, "tool", "q"), (None, 1, "tool", "r"), (None, 2, "user", "s"), (None, None, None, None), (2, 0, "user", ""), (2, -3, "user", "neg"), (3, 5, "tool", "lost"), (3, 5, "tool", "lost")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    df.write.parquet(f"{tmp_path}/conversations.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW conversations AS SELECT * FROM '{tmp_path}/conversations.parquet/*.parquet'")
    want = rows_of_duck(con, chat.ORACLE)
    for n in (1, 7):
        extra = df.withColumns({"name": F.lit("x"), "_uid": F.lit(1), "position": F.lit(0)}).repartition(n)
        assert rows_of_spark(chat.link_conversations(extra)) == want
    got = chat.link_conversations(df).where("conv_id IS NULL AND name IS NOT NULL").collect()
    assert len(got) == 2 and all(r["n_results"] == 0 for r in got)  # null identifiers link to nothing


def test_canonical_json(spark):
    df = spark.createDataFrame([('{ "b" : [1, {"z": 1, "y": "\\u00e9"}], "a" : "q\\"\\n" }',), ("nope",)], "j string")
    got = [r[0] for r in df.select(chat.canonical(F.col("j"))).collect()]
    assert got == ['{"a":"q\\"\\n","b":[1,{"y":"é","z":1}]}', None]


def test_links_order_and_status(spark):
    calls = [
        (1, 1, "a", "add", '{"b": 2, "a": 1}', []), (1, 3, "b", "add", '{"a": 2}', ["a"]), (1, 5, "c", "add", '{"a": 3}', ["d"]),
        (1, 7, "d", "add", '{"a": 4}', ["d"]), (2, 1, "e", "add", '{"a": 5}', ["gone"]), (2, 2, "e", "add", None, None), (None, None, None, None, None, None),
    ]
    results = [("a", "two"), ("a", "one"), ("b", None), ("zz", "lost"), (None, "nobody's")]
    got = chat.link(spark.createDataFrame(calls, CALLS), spark.createDataFrame(results, "call_id string, content string"), SCHEMAS).collect()
    by = {(r["call_id"], r["position"]): r for r in got}
    assert (by["a", 0]["status"], by["a", 0]["n_results"], json.loads(by["a", 0]["record"])["result"]) == ("linked", 2, "one")
    assert by["b", 1]["status"] == "linked" and json.loads(by["b", 1]["record"])["after"] == ["a"]
    assert by["c", 2]["status"] == by["d", 3]["status"] == by["e", 0]["status"] == "bad_dependency"
    assert by["e", 1]["status"] == "unanswered" and by["e", 1]["valid"] is False
    assert {r["call_id"] for r in got if r["status"] == "orphan"} == {"zz", None}
    assert by["a", 0]["record"] == '{"after":[],"arguments":{"a":1,"b":2},"id":"a","name":"add","result":"one","valid":true}'
    assert len(got) == len(calls) + 2


def test_repeated_turns_and_empty(spark):
    rows = [(1, 0, "user", "hi"), (1, 0, "user", "hi"), (1, 1, "assistant", "x"), (1, 1, "assistant", "y"), (None, None, None, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = chat.link_conversations(df).collect()
    assert sorted(r["position"] for r in got if r["status"] == "linked") == [0, 1] and {r["n_results"] for r in got if r["status"] == "linked"} == {2}
    assert chat.link_conversations(df.where("false")).count() == 0


def test_long_conversation(spark):
    df = spark.range(120_000).select(F.lit(1).alias("conv_id"), "id", F.when(F.col("id") % 2 == 0, "user").otherwise("assistant").alias("role"), F.lit("t").alias("text")).withColumnRenamed("id", "turn")
    got = chat.link_conversations(df)
    assert got.where("position * 2 = split(call_id, ':')[1] AND status = 'linked'").count() == 60_000


def test_topological_order(spark):
    calls = [
        (1, 1, "p", ["q"]), (1, 1, "q", ["r"]), (1, 1, "r", []), (1, 2, "s", ["u"]), (1, 3, "t", ["s"]), (1, 4, "u", ["r"]), (1, 5, "v", ["t", "u"]),  # parallel calls, and one of a later turn
        (2, 1, "p", []), (2, 3, "q", ["p"]), (2, 4, "w", ["v"]),  # identifiers reused; v is another conversation's
        (3, 1, "a", ["b"]), (3, 2, "b", ["a"]), (3, 3, "c", ["b"]), (3, 4, "d", []), (None, 1, "n", ["o"]), (None, 2, "o", []),  # a cycle, and one after it
    ]
    rows = [(c, t, i, "add", "{}", a) for c, t, i, a in calls]
    got = chat.link(spark.createDataFrame(rows, CALLS).repartition(5), spark.createDataFrame([], "call_id string, content string"), SCHEMAS).collect()
    order = lambda c: "".join(r["call_id"] for r in sorted((r for r in got if r["conv_id"] == c), key=lambda r: r["position"]))
    assert (order(1), order(2), order(3), order(None)) == ("rqpustv", "pqw", "abcd", "on")
    assert sorted((r["conv_id"], r["call_id"]) for r in got if r["status"] == "bad_dependency") == [(2, "w"), (3, "a"), (3, "b")]


def test_random_dependencies_are_sorted(spark):
    import random

    r = random.Random(3)
    rows = []
    for c in range(30):
        rank = r.sample(range(12), 12)
        rows += [(c, r.randrange(6), f"{k}", "add", "{}", [f"{d}" for d in range(12) if rank[d] < rank[k] and r.random() < 0.25]) for k in range(12)]
    got = chat.link(spark.createDataFrame(rows, CALLS), spark.createDataFrame([], "call_id string, content string"), SCHEMAS).collect()
    at = {(x["conv_id"], x["call_id"]): x["position"] for x in got}
    assert len(at) == len(rows) and {x["status"] for x in got} == {"unanswered"}
    assert all(at[c, d] < at[c, k] for c, _, k, _, _, after in rows for d in after)


def test_every_result_is_kept(spark, tmp_path):
    from hypertriad.llm.queries import queries

    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", "y"), (1, 1, "assistant", "x"), (1, 1, "assistant", "x"), (1, 4, "assistant", "late"), (2, 1, "tool", None)]
    rows += [(None, None, None, f"n{k}") for k in range(3)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    got = queries()["op4_chat_results"](spark, str(tmp_path)).collect()
    assert len(got) == 8
    one = sorted((r["number"], r["content"], r["status"]) for r in got if r["call_id"] == "1:0")
    assert [x[0] for x in one] == [0, 1, 2] and sorted(x[1] for x in one) == ["x", "x", "y"] and {x[2] for x in one} == {"answer"}
    assert sorted(((r["call_id"], r["content"] or "") for r in got if r["status"] == "orphan"), key=str) == [("1:3", "late"), ("2:0", ""), (None, "n0"), (None, "n1"), (None, "n2")]
