"""Pieces that several operators share."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kbspark.session import cut  # noqa: F401  (re-exported)

# ASCII blanks as the word pattern [^\x20\x09-\x0D]+ leaves them out.
BLANKS = " \t\n\x0b\x0c\r"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def give_back() -> None:
    """Return to the system what this process has freed: a worker lives on beside the JVM, which needs the memory next."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def rest(spark: SparkSession) -> None:
    """Have the executors' JVMs collect their garbage and give free heap back to the system, before Python workers beside
    them need the memory: a heap that a join has filled stays as large as it was. One short task for each core."""
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.java_method(F.lit("java.lang.System"), F.lit("gc"))).write.format("noop").mode("overwrite").save()


def slices(batches: Iterator[pa.RecordBatch], rows: int = 256) -> Iterator[pa.RecordBatch]:
    """The batches in short pieces, so that few rows at a time become Python objects."""
    for b in batches:
        for low in range(0, b.num_rows, rows):
            yield b.slice(low, rows)
        del b
        give_back()


def unused(name: str, *frames: DataFrame) -> str:
    """A column name that none of the frames has in any case, made from name."""
    taken = {c.lower() for df in frames for c in df.columns}
    while (name := f"{name}_") in taken:
        pass
    return name


def if_few(df: DataFrame, rows: int) -> DataFrame:
    """df, to be broadcast if it has at most so many rows (callers pass rows of a few numbers); stops counting one beyond."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def ranked(df: DataFrame, order: list[str], weight: str | None = None) -> tuple[DataFrame, int, int]:
    """Number the rows of df from 0 in the total order given, without a one-partition window.

    A range-partitioned sort is materialised once; each row's partition and place there come from
    monotonically_increasing_id, and the few per-partition totals give every partition its first number.
    Adds __rank (and __before, the sum of weight over earlier rows, if weight is given). Returns the frame,
    the number of rows and the total weight. Ties in the order get distinct numbers.
    """
    from pyspark.sql import Window

    placed = cut(df.orderBy(*order).withColumn("__mono", F.monotonically_increasing_id()))
    placed = placed.withColumn("__pid", F.shiftright("__mono", 33)).withColumn("__idx", F.col("__mono").bitwiseAND(F.lit((1 << 33) - 1)))
    w = F.col(weight) if weight else F.lit(0)
    sums = placed.groupBy("__pid").agg(F.count(F.lit(1)).alias("__n"), F.sum(w.cast("long")).alias("__w"))
    # One row for each partition of the sort: small whatever the input is.
    upto = Window.partitionBy(F.lit(0)).orderBy("__pid").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("__pid", F.coalesce(F.sum("__n").over(upto), F.lit(0)).alias("__first"), F.coalesce(F.sum("__w").over(upto), F.lit(0)).alias("__w0"))
    total = sums.agg(F.sum("__n"), F.sum("__w")).first()
    out = placed.join(F.broadcast(starts), "__pid").withColumn("__rank", F.col("__first") + F.col("__idx"))
    if weight:
        inside = Window.partitionBy("__pid").orderBy("__idx").rowsBetween(Window.unboundedPreceding, -1)
        out = out.withColumn("__before", F.col("__w0") + F.coalesce(F.sum(w.cast("long")).over(inside), F.lit(0)))
    return out.drop("__mono", "__pid", "__idx", "__first", "__w0"), total[0] or 0, total[1] or 0
