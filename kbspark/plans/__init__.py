"""Choices of physical strategy by checked sizes, made when a plan is built."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kbspark.operators import dictionary, vectors

BROADCAST_BYTES = 64 << 20


def small(df: DataFrame, rows: int) -> bool:
    """Whether df has at most so many rows; stops counting one beyond."""
    return df.limit(rows + 1).count() <= rows


def sized_join(left: DataFrame, right: DataFrame, on, how: str = "inner", rows: int = 1_000_000) -> DataFrame:
    """Broadcast the right side if it is small by count, else leave a shuffle join with skew handling."""
    return left.join(F.broadcast(right) if small(right, rows) else right, on, how)


def match_plan(docs: DataFrame, key: str, text: str, synonyms: DataFrame, max_patterns: int = 1_000_000) -> DataFrame:
    """The automaton while its arrays fit every worker, the n-gram join beyond."""
    if small(synonyms, max_patterns):
        return dictionary.match(docs, key, text, dictionary.build(synonyms)).select(key, "record_id", "first", "last")
    return dictionary.match_ngrams(docs, key, text, synonyms)


def knn_plan(queries: DataFrame, base: DataFrame, k: int, approximate: bool = False, cells: int = 1024, probes: int = 32) -> DataFrame:
    """Exact blocks at every size; inverted cells only where the caller asks for an approximate answer, whose recall at
    given cells and probes `measure.neighbour_recall` tells."""
    if not approximate:
        return vectors.knn_blocks(queries, base, k)
    return vectors.ivf(queries, base, k, vectors.cells(base, cells), probes)
