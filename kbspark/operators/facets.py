"""Faceted search over narrow side tables (record_id, slot, value): exact, partial and wildcard conditions."""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def build(records: DataFrame) -> DataFrame:
    """The side table of records with slots; partition by slot and sort by value when it is written."""
    return records.select("record_id", F.explode("slots").alias("slot", "vs")).select("record_id", "slot", F.explode("vs").alias("value"))


def part_tags(part: DataFrame) -> DataFrame:
    wide = part.select(F.col("p_partkey").alias("record_id"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.col("p_size").cast("string").alias("size"))
    return wide.unpivot("record_id", ["brand", "type", "size"], "slot", "value")


def search(tags: DataFrame, wanted: list[tuple[str, Column]], at_least: int | None = None) -> DataFrame:
    """Ids that meet all conditions (or at least so many): one pushed filter, one aggregation, no join."""
    hit = [F.when((F.col("slot") == slot) & cond, F.lit(i)) for i, (slot, cond) in enumerate(wanted)]
    met = tags.where(reduce(or_, [(F.col("slot") == slot) & cond for slot, cond in wanted]))
    n = F.size(F.collect_set(F.coalesce(*hit)))
    return met.groupBy("record_id").agg(n.alias("n")).where(F.col("n") >= (at_least or len(wanted))).select("record_id")


def counts(tags: DataFrame) -> DataFrame:
    return tags.groupBy("slot", "value").agg(F.count_distinct("record_id").alias("n"))


def layout(records: DataFrame, path: str) -> None:
    """Attribute index as files: a folder for each type, rows sorted by id, bloom filters on ids and names."""
    sort = records.repartition("type", F.pmod(F.xxhash64("record_id"), F.lit(16))).sortWithinPartitions("type", "record_id")
    writer = sort.write.mode("overwrite").partitionBy("type")
    for c in ("record_id", "name"):
        writer = writer.option(f"parquet.bloom.filter.enabled#{c}", "true")
    writer.parquet(path)
