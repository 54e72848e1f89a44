"""Few-hop search on the relation graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kbspark.session import cut


def hops(edges: DataFrame, seeds: DataFrame, relations: list[str], max_hops: int, direction: str = "out") -> DataFrame:
    """seed, id and hop of all records within max_hops of each seed by the relations given.

    The relation filter is pushed into every hop; a frontier leaves out what its seed has seen, so cycles end. Each
    hop is materialised, as the next one reads it twice.
    """
    e = edges.where(F.col("relation").isin(relations)).select(F.col("subject").alias("s"), F.col("object").alias("o"))
    if direction == "in":
        e = e.select(F.col("o").alias("s"), F.col("s").alias("o"))
    elif direction == "both":
        e = e.union(e.select(F.col("o").alias("s"), F.col("s").alias("o")))
    seen = seeds.select("seed", F.col("seed").alias("id"), F.lit(0).alias("hop")).distinct()
    frontier = seen
    for hop in range(1, max_hops + 1):
        step = frontier.join(e, F.col("id") == F.col("s")).select("seed", F.col("o").alias("id"), F.lit(hop).alias("hop")).distinct()
        frontier = cut(step.join(seen.select("seed", "id"), ["seed", "id"], "left_anti").select("seed", "id", "hop"))
        if frontier.isEmpty():
            break
        seen = seen.union(frontier)
    return seen


def with_relation_records(edges: DataFrame, records: DataFrame) -> DataFrame:
    """Edges whose relation is a record itself, with that record's name and content."""
    r = records.select(F.col("record_id").alias("relation_id"), F.col("name").alias("relation_name"), F.col("content").alias("relation_content"))
    return edges.join(r, "relation_id", "left")
