"""Keys under which experiences are indexed: sketches of the question, the query, its header, its trace."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NUMERAL = r"(?<![\p{L}\p{N}_#])\p{N}+(?![\p{L}\p{N}_])"
HITS = "array<struct<start:int,stop:int,label:string>>"


def sketch(questions: DataFrame, hits: DataFrame) -> DataFrame:
    """q_id and sketch of all questions (q_id, text): each hit (q_id, start, stop, label; none overlaps another) becomes
    [label], each other numeral [VALUE]. A null text has a null sketch."""
    ordered = F.sort_array(F.collect_list(F.struct(F.col("start").cast("int").alias("start"), F.col("stop").cast("int").alias("stop"), "label")))
    j = questions.select("q_id", "text").join(hits.groupBy("q_id").agg(ordered.alias("hs")), "q_id", "left")
    plain = lambda c: F.regexp_replace(c, NUMERAL, "[VALUE]")
    step = lambda s, h: F.struct(F.concat(s["out"], plain(F.substr("text", s["at"] + 1, h["start"] - s["at"])), F.lit("["), h["label"], F.lit("]")).alias("out"), h["stop"].alias("at"))
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))
    made = F.aggregate(F.coalesce("hs", F.array().cast(HITS)), start, step, lambda s: F.concat(s["out"], plain(F.substr("text", s["at"] + 1, F.length("text")))))
    return j.select("q_id", made.alias("sketch"))


def sql_key(sql: Column) -> Column:
    """The query without comments, blanks made one."""
    bare = F.regexp_replace(F.regexp_replace(sql, r"--[^\n]*", " "), r"(?s)/\*.*?\*/", " ")
    return F.trim(F.regexp_replace(bare, r"\s+", " "))


def header_key(sql: Column) -> Column:
    """The texts of a profiled query's header: its line comments before the query begins."""
    head = F.regexp_extract(sql, r"\A((?:[ \t]*--[^\n]*\n)*)", 1)
    return F.array_join(F.regexp_extract_all(head, F.lit(r"--[ \t]*([^\n]*)"), F.lit(1)), " ")


def trace_key(trace: Column, most: int = 1_000) -> Column:
    """The first words of a trace, `most` at the most, blanks made one."""
    return F.array_join(F.slice(F.split(F.trim(F.regexp_replace(trace, r"\s+", " ")), " "), 1, most), " ")
