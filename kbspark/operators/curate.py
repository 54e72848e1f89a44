"""Curation of training tuples: hardness, quality, variety, selection, export."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kbspark.functions.text import ngrams, words
from kbspark.operators.vectors import knn_blocks


def hardness(evals: DataFrame) -> DataFrame:
    """q_id and h: how many samples failed. evals: q_id, correct."""
    return evals.groupBy("q_id").agg(F.count_if(F.coalesce(F.col("correct"), F.lit(0)) == 0).alias("h"))


def brevity(tokens: Column, low: int = 20, high: int = 400) -> Column:
    """10 up to `low` tokens, 0 from `high` on, linear between."""
    return F.round(F.greatest(F.lit(0.0), F.least(F.lit(10.0), 10.0 * (high - tokens) / (high - low))), 6)


def non_repetition(text: Column, n: int = 3) -> Column:
    """10 times the share of distinct word n-grams."""
    g = ngrams(words(F.lower(text)), n)
    return F.round(F.when(F.size(g) == 0, 10.0).otherwise(10.0 * F.size(F.array_distinct(g)) / F.size(g)), 6)


DIMENSIONS = 7


def quality(judged: list[Column], tokens: Column) -> Column:
    """Sum of six judged dimensions and brevity, each 0 to 10: 0 to 70."""
    if len(judged) != DIMENSIONS - 1:
        raise ValueError("six judged dimensions")
    clip = lambda c: F.greatest(F.lit(0.0), F.least(F.lit(10.0), c.cast("double")))
    total = brevity(tokens)
    for c in judged:
        total = total + clip(c)
    return total


def normalise(df: DataFrame, score: str) -> DataFrame:
    """Adds z and shaped: scores on a normal scale of mean 5 and deviation 2, cut to 0..10."""
    m = df.agg(F.avg(score).alias("__m"), F.stddev_pop(score).alias("__s"))
    z = (F.col(score) - F.col("__m")) / F.when(F.col("__s") == 0, 1.0).otherwise(F.col("__s"))
    out = df.join(F.broadcast(m)).withColumn("z", z)
    return out.withColumn("shaped", F.greatest(F.lit(0.0), F.least(F.lit(10.0), 5 + 2 * F.col("z")))).drop("__m", "__s")


def variety_freq(df: DataFrame, keys: list[str]) -> DataFrame:
    """keys and v: one over how often the group occurs; counted before anything is joined back."""
    return df.groupBy(*keys).agg((F.lit(1.0) / F.count(F.lit(1))).alias("v"))


def variety_knn(vectors: DataFrame, k: int = 5) -> DataFrame:
    """id and v: mean distance (1 - cosine) to the k nearest others. vectors: id, vec.

    Every row is a query; queries go in blocks, so the neighbours are exact at every size.
    """
    near = knn_blocks(vectors.select(F.col("id").alias("q"), "vec"), vectors, k)
    return near.groupBy(F.col("q").alias("id")).agg(F.round(F.avg(1 - F.col("score")), 6).alias("v"))


def select(df: DataFrame, top: int, alpha: float = 1.0, beta: float = 0.1, gamma: float = 1.0, tie: str = "id") -> DataFrame:
    """The `top` rows by alpha * hardness + beta * quality + gamma * variety; ties by id."""
    total = F.round(alpha * F.col("h") + beta * F.col("q") + gamma * F.col("v"), 6)
    return df.withColumn("total", total).orderBy(F.desc("total"), tie).limit(top)


def random_choice(df: DataFrame, top: int, key: str = "id") -> DataFrame:
    """Baseline: a fixed pseudo-random choice."""
    return df.orderBy(F.xxhash64(key), key).limit(top)


def messages(turns: DataFrame, key: str = "conv_id") -> DataFrame:
    """key and messages: the ordered turns of each conversation as JSON."""
    return turns.groupBy(key).agg(F.to_json(F.transform(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))), lambda t: F.struct(t["role"].alias("role"), t["text"].alias("content")))).alias("messages"))


def training_messages(examples: DataFrame, trace: bool = True, records: bool = True) -> DataFrame:
    """q_id and messages of examples (q_id, question, sql, trace, records: texts): a system turn of the records, if asked
    for and there are any, the question, and the answer, after its trace if asked for. Null texts are empty."""
    turn = lambda role, text: F.struct(F.lit(role).alias("role"), text.alias("content"))
    text = lambda c: F.coalesce(F.col(c), F.lit(""))
    answer = F.when(F.lit(trace) & (F.length(text("trace")) > 0), F.concat(text("trace"), F.lit("\n\n"), text("sql"))).otherwise(text("sql"))
    turns = F.array(turn("user", text("question")), turn("assistant", answer))
    known = F.array(turn("system", F.array_join("records", "\n")))
    with_known = F.when(F.lit(records) & (F.size(F.coalesce("records", F.array().cast("array<string>"))) > 0), F.concat(known, turns)).otherwise(turns)
    return examples.select("q_id", F.to_json(with_known).alias("messages"))
