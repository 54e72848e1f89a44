"""Fusion of ranked lists: round-robin with duplicates taken at their first turn, or a scorer over all."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def round_robin(lists: DataFrame, k: int) -> DataFrame:
    """lists: q, index_no, rank, id. Turn order is rank, then index; an id counts at its first turn."""
    first = lists.groupBy("q", "id").agg(F.min(F.struct("rank", "index_no")).alias("turn"))
    w = Window.partitionBy("q").orderBy("turn", "id")
    return first.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k).select("q", F.col("place").alias("rank"), "id")


def rerank(lists: DataFrame, scorer: Column, k: int) -> DataFrame:
    one = lists.groupBy("q", "id").agg(F.max(scorer).alias("score"))
    w = Window.partitionBy("q").orderBy(F.desc("score"), "id")
    return one.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("q", "rank", "id", "score")
