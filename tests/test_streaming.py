"""Streams against their batch twins."""

from pyspark.sql import functions as F

from kbspark.sources.tables import table
from kbspark.streaming import lifelong


def slices(spark, sf, path, n=5):
    raw = spark.read.parquet(f"{sf}/events.parquet")
    top = raw.agg(F.max("event_id")).first()[0] + 1
    for i in range(n):
        raw.where((F.col("event_id") >= top * i // n) & (F.col("event_id") < top * (i + 1) // n)).coalesce(1).write.mode("append").parquet(str(path))
    return raw.schema


def drained(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name)


def test_usage_and_dedupe(spark, sf, tmp_path):
    schema = slices(spark, sf, tmp_path / "in")
    events = lifelong.read_events(spark, str(tmp_path / "in"), schema, files=100)
    got = {(str(r["start"]), r["event_type"]): r["n"] for r in drained(lifelong.usage(events, late="60 days"), "usage_t", "complete").collect()}
    want = table(spark, sf, "events").groupBy(F.window("ts", "1 day"), "event_type").count()
    assert got == {(str(r["window"]["start"]), r["event_type"]): r["count"] for r in want.collect()}
    once = drained(lifelong.first_askings(events, ["user_id", "event_type"], "60 days"), "once_t", "append")
    assert once.count() == table(spark, sf, "events").select("user_id", "event_type").distinct().count()


def test_late_rows_drop(spark, sf, tmp_path):
    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    base = spark.read.parquet(f"{sf}/events.parquet").orderBy("event_id")
    path = str(tmp_path / "in")
    for i, part in enumerate((base.where("event_id < 500"), base.where("event_id >= 500"), base.where("event_id = 999").withColumn("ts", F.lit("2020-01-01").cast("timestamp_ntz")))):
        part.coalesce(1).write.parquet(f"{path}/p{i}")
    events = lifelong.read_events(spark, f"{path}/*", schema, files=1)
    got = drained(lifelong.usage(events, late="1 day"), "late_t", "append")
    assert got.where("start < '2021-01-01'").count() == 0


def test_labels_join(spark, sf, tmp_path):
    schema = slices(spark, sf, tmp_path / "in", 2)
    e = lifelong.read_events(spark, str(tmp_path / "in"), schema, files=100)
    q = e.select(F.col("event_id").alias("q_id"), "ts")
    lab = e.where("event_id % 2 = 0").select(F.col("event_id").alias("q_id"), (F.col("ts") + F.expr("interval 2 hours")).alias("labelled_at"), F.lit("SELECT 1").alias("gold_sql"))
    got = drained(lifelong.with_labels(q, lab, late="60 days"), "labels_t", "append")
    assert got.count() == table(spark, sf, "events").where("event_id % 2 = 0").count()


def test_user_defaults(spark, sf, tmp_path):
    schema = slices(spark, sf, tmp_path / "in", 2)
    events = lifelong.read_events(spark, str(tmp_path / "in"), schema, files=1)
    last = drained(lifelong.user_defaults(events), "defaults_t", "update").groupBy("user_id").agg(F.max(F.struct("n", "learnt")).alias("m"))
    want = table(spark, sf, "events").groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.max("count").alias("n"))
    assert {(r["user_id"], r["m"]["n"]) for r in last.collect()} == {(r["user_id"], r["n"]) for r in want.collect()}


def test_loop_answers_from_the_past(spark, sf, tmp_path):
    schema = slices(spark, sf, tmp_path / "in", 3)
    stream = lifelong.read_events(spark, str(tmp_path / "in"), schema, files=1)
    item = F.col("user_id")
    answer = lambda df, kb: df.select("event_id", item.alias("item")).join(kb.withColumn("known", F.lit(True)) if kb is not None else df.select(item.alias("item"), F.lit(True).alias("known")).limit(0), "item", "left").select("event_id", F.coalesce("known", F.lit(False)).alias("known"))
    learn = lambda kb, df: (df.select(item.alias("item")) if kb is None else df.select(item.alias("item")).union(kb)).distinct()
    lifelong.run(stream, answer, learn, str(tmp_path / "store"), str(tmp_path / "ckpt")).awaitTermination(120)
    answers = [spark.read.parquet(f"{tmp_path}/store/answers/{i}") for i in range(3)]
    assert answers[0].where("known").count() == 0 and answers[2].where("known").count() > 0
    assert sum(a.count() for a in answers) == table(spark, sf, "events").count()
