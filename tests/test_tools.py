"""Keys of experiences and training messages on small examples."""

import json

from kbspark.operators import curate, serializers
from pyspark.sql import functions as F


def test_sketch(spark):
    q = spark.createDataFrame([(1, "List the top 10 of Asia in A4 2019"), (2, "no 7up, 7 up"), (3, None), (4, "")], "q_id long, text string")
    at = "List the top 10 of Asia in A4 2019".index("Asia")
    hits = spark.createDataFrame([(1, at, at + 4, "R_NAME as ENUM")], "q_id long, start long, stop long, label string")
    got = dict(map(tuple, serializers.sketch(q, hits).collect()))
    assert got == {1: "List the top [VALUE] of [R_NAME as ENUM] in A4 [VALUE]", 2: "no 7up, [VALUE] up", 3: None, 4: ""}


def test_keys(spark):
    sql = "-- question: how many\n-- result: n bigint\n\n/* shown */ SELECT  1 -- one\n FROM t"
    row = spark.createDataFrame([(sql, " a  b\nc ")], "s string, t string").select(serializers.sql_key(F.col("s")), serializers.header_key(F.col("s")), serializers.trace_key(F.col("t"), 2)).first()
    assert tuple(row) == ("SELECT 1 FROM t", "question: how many result: n bigint", "a b")


def test_training_messages(spark):
    rows = spark.createDataFrame([(1, "q", "s", "t", ["x", "y"]), (2, "q", "s", None, None)], "q_id long, question string, sql string, trace string, records array<string>")
    read = lambda **k: {r[0]: [(m["role"], m["content"]) for m in json.loads(r[1])] for r in curate.training_messages(rows, **k).collect()}
    assert read() == {1: [("system", "x\ny"), ("user", "q"), ("assistant", "t\n\ns")], 2: [("user", "q"), ("assistant", "s")]}
    assert read(trace=False, records=False) == {i: [("user", "q"), ("assistant", "s")] for i in (1, 2)}


def test_scanned_columns_read_every_column(spark, sf):
    """Each column's values are counted by tasks, and the columns are those of the schemas."""
    from kbspark.sources.tables import catalog
    from kbspark.workloads.tool_queries import scanned_columns

    made = scanned_columns(spark, sf)
    assert sorted(map(tuple, made.collect())) == sorted((r["tab"], r["col"]) for r in catalog(spark, sf).collect())
    plan = made.groupBy().count()._jdf.queryExecution().executedPlan().toString()
    assert all(c in plan for c in ("l_shipdate", "props", "c_address"[:2], "o_orderdate"))
