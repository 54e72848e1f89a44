"""The lifelong loop: questions come in batches or as a stream; each batch is answered from what was known before it,
then its entries are merged. Streams of usage statistics, repeated questions, late labels and per-user defaults."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def curve(items: DataFrame) -> DataFrame:
    """batch, n, known_share and running, from batch and item: an item is known after its first batch."""
    first = items.groupBy("item").agg(F.min("batch").alias("first"))
    by = items.join(first, "item").groupBy("batch").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("batch") > F.col("first")).alias("known"))
    run = Window.partitionBy(F.lit(0)).orderBy("batch").rowsBetween(Window.unboundedPreceding, 0)  # one row a batch
    return by.select("batch", "n", F.round(F.col("known") / F.col("n"), 6).alias("known_share"), F.round(F.sum("known").over(run) / F.sum("n").over(run), 6).alias("running"))


def read_events(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    """A file stream of events whose times are made UTC timestamps, as watermarks refuse those without zone."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def usage(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Counts by window and type; rows later than the watermark are dropped."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(w, "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "1 hour", late: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def first_askings(questions: DataFrame, keys: list[str], late: str = "1 day") -> DataFrame:
    """Each question once within the watermark."""
    return questions.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def with_labels(questions: DataFrame, labels: DataFrame, within: str = "3 hours", late: str = "1 day") -> DataFrame:
    """Questions joined with the labels that come within a time after them: a stream-stream join with bounded state."""
    q = questions.withWatermark("ts", late).alias("q")
    lab = labels.withWatermark("labelled_at", late).alias("l")
    on = F.expr(f"q.q_id = l.q_id AND l.labelled_at >= q.ts AND l.labelled_at <= q.ts + INTERVAL {within}")
    return q.join(lab, on).select("q.q_id", "q.ts", "l.labelled_at", "l.gold_sql")


def user_defaults(events: DataFrame, value: str = "event_type") -> DataFrame:
    """user_id, learnt, n: the value that each user has chosen most often so far, in keyed state with a timeout."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        names, counts = state.get if state.exists else ("", "")
        seen = dict(zip(names.split("|"), map(int, counts.split("|")), strict=True)) if names else {}
        for f in frames:
            for v, n in f[value].value_counts().items():
                seen[v] = seen.get(v, 0) + int(n)
        state.update(("|".join(seen), "|".join(map(str, seen.values()))))
        state.setTimeoutDuration(3_600_000)
        best = min(seen, key=lambda v: (-seen[v], v))
        yield pd.DataFrame({"user_id": [key[0]], "learnt": [best], "n": [seen[best]]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, learnt string, n long", "names string, counts string", "update", GroupStateTimeout.ProcessingTimeTimeout)


def run(stream: DataFrame, answer: Callable[[DataFrame, DataFrame | None], DataFrame], learn: Callable[[DataFrame | None, DataFrame], DataFrame], store: str, checkpoint: str):
    """Start the loop: each micro-batch is answered with the last snapshot, then a new snapshot is written.

    Snapshots and answers are files named by batch id, so a batch that is run again overwrites its own output.
    """

    def batch(df: DataFrame, batch_id: int) -> None:
        spark = df.sparkSession
        known = spark.read.parquet(f"{store}/kb/{batch_id - 1}") if batch_id else None
        df.persist()
        answer(df, known).write.mode("overwrite").parquet(f"{store}/answers/{batch_id}")
        learn(known, df).write.mode("overwrite").parquet(f"{store}/kb/{batch_id}")
        df.unpersist()

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
