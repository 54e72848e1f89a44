"""Matching keywords with values: n-gram containment by inverted join, edit distance, hashed vectors, MinHash."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kbspark.session import cut


def grams(text: Column, n: int = 3) -> Column:
    """Distinct character n-grams; a shorter text is its own gram."""
    m = F.length(text) - n + 1
    return F.when(m > 0, F.array_distinct(F.transform(F.sequence(F.lit(1), m), lambda i: F.substr(text, i, F.lit(n))))).otherwise(F.array(text))


def containment(keywords: DataFrame, values: DataFrame, n: int = 3) -> DataFrame:
    """keyword, value, score: the share of the keyword's n-grams that the value has, for pairs that share one.

    Postings join on grams: work grows with shared grams, never with all pairs. It isn't symmetric.
    """
    kg = keywords.select("keyword", F.explode(grams(F.lower("keyword"), n)).alias("g"))
    vg = values.select("value", F.explode(grams(F.lower("value"), n)).alias("g")).distinct()
    need = keywords.select("keyword", F.size(grams(F.lower("keyword"), n)).alias("need")).distinct()
    hits = kg.join(vg, "g").groupBy("keyword", "value").agg(F.count(F.lit(1)).alias("n"))
    return hits.join(need, "keyword").select("keyword", "value", F.round(F.col("n") / F.col("need"), 6).alias("score"))


MAX_KEYWORDS = 100_000


def by_blocks(keywords: DataFrame, run) -> DataFrame:
    """run on broadcast blocks of the keywords: a query set of any size, at most about MAX_KEYWORDS at a time."""
    parts = -(-2 * keywords.count() // MAX_KEYWORDS) or 1
    block = lambda i: keywords if parts == 1 else keywords.where(F.pmod(F.xxhash64("keyword"), F.lit(parts)) == i)
    return reduce(DataFrame.union, (run(F.broadcast(block(i))) for i in range(parts)))


def edit(keywords: DataFrame, values: DataFrame) -> DataFrame:
    """Baseline: negated edit distance of every value to every keyword of a query set, which is broadcast in blocks."""
    return by_blocks(keywords, lambda ks: values.join(ks).select("keyword", "value", (-F.levenshtein("keyword", F.lower("value"))).alias("score")))


def encode(df: DataFrame, column: str, keep: list[str], dim: int = 256, n: int = 3) -> DataFrame:
    """keep and vec: hashed n-gram vectors of unit length, a frozen encoder that needs no model."""
    import zlib

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = []
            for t in b.column(b.num_columns - 1).to_pylist():
                v, padded = np.zeros(dim, np.float32), f" {(t or '').lower()} "
                for i in range(len(padded) - n + 1):
                    h = zlib.crc32(padded[i : i + n].encode())
                    v[h % dim] += 1 if h & 0x10000 else -1
                made.append((v / (np.linalg.norm(v) or 1)).tolist())
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(made, pa.list_(pa.float32()))], [*b.schema.names[:-1], "vec"])

    rows = df.select(*keep, F.col(column).alias("__text"))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    return rows.mapInArrow(run, f"{kinds}, vec array<float>")


def dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def semantic(keywords: DataFrame, values: DataFrame) -> DataFrame:
    """Cosine of hashed vectors: each block of values against the broadcast query set."""
    k, v = encode(keywords, "keyword", ["keyword"]), encode(values, "value", ["value"])
    return by_blocks(k.withColumnRenamed("vec", "kvec"), lambda ks: v.join(ks).select("keyword", "value", F.round(dot("vec", "kvec"), 6).alias("score")))


def combined(keywords: DataFrame, values: DataFrame, weight: float = 0.5) -> DataFrame:
    """Lexical and semantic scores together; a pair missing on the lexical side counts 0 there."""
    s = semantic(keywords, values).withColumnRenamed("score", "s")
    lex = containment(keywords, values).withColumnRenamed("score", "l")
    return s.join(lex, ["keyword", "value"], "left").select("keyword", "value", F.round(weight * F.coalesce("l", F.lit(0.0)) + (1 - weight) * F.col("s"), 6).alias("score"))


def top(scored: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("keyword").orderBy(F.desc("score"), "value")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def shingle_sets(docs: DataFrame, words: int = 5) -> DataFrame:
    """doc_id and sh, the sorted hashes of the text's distinct word shingles (fewer words: one shingle)."""
    ws = F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "")
    n = F.size("ws") - words + 1
    sh = F.when(n > 0, F.transform(F.sequence(F.lit(1), n), lambda i: F.xxhash64(F.array_join(F.slice("ws", i, words), " ")))).otherwise(F.array(F.xxhash64(F.array_join("ws", " "))))
    return docs.select("doc_id", F.coalesce(ws, F.array().cast("array<string>")).alias("ws")).select("doc_id", F.explode(F.array(F.array_sort(F.array_distinct(sh)))).alias("sh"))


def minhash_pairs(items: DataFrame, threshold: float = 0.8, bands: int = 20, rows: int = 5) -> DataFrame:
    """Baseline: a < b and jaccard of items (doc_id, sh) that reach the threshold, by banded MinHash.

    Bands propose pairs, exact Jaccard confirms them. A pair at just 0.8 is missed with a chance of 0.04 %; the chance
    falls with `bands`.
    """
    sigs = [F.array_min(F.transform("sh", lambda x: F.xxhash64(x, F.lit(i)))) for i in range(bands * rows)]  # noqa: B023
    keyed = items.select("doc_id", F.posexplode(F.array(*(F.xxhash64(*sigs[b * rows : (b + 1) * rows]) for b in range(bands)))).alias("band", "key"))
    left, right = keyed.withColumnRenamed("doc_id", "a"), keyed.withColumnRenamed("doc_id", "b")
    pairs = left.join(right, ["band", "key"]).where("a < b").select("a", "b").distinct()
    x = items.select(F.col("doc_id").alias("a"), F.col("sh").alias("sa"))
    y = items.select(F.col("doc_id").alias("b"), F.col("sh").alias("sb"))
    both = pairs.join(x, "a").join(y, "b")
    j = F.size(F.array_intersect("sa", "sb")) / F.size(F.array_union("sa", "sb"))
    return both.select("a", "b", F.round(j, 6).alias("jaccard")).where(F.col("jaccard") >= threshold)


def minhash_links(docs: DataFrame, threshold: float = 0.8, bands: int = 20, rows: int = 5, words: int = 5) -> DataFrame:
    """doc_id, class_id and n_links of all documents. Texts with equal sets of shingles are one class, named by its
    smallest doc_id; a document is linked with the others of its class and with all of each class near its own."""
    sets = cut(shingle_sets(docs, words).select("doc_id", "sh", F.xxhash64("sh").alias("h"), F.size("sh").alias("m")))
    classes = cut(sets.groupBy("h", "m", "sh").agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("n")))
    pairs = minhash_pairs(classes, threshold, bands, rows).select("a", "b")
    sizes = classes.select("doc_id", "n")
    near = pairs.union(pairs.select("b", "a")).join(sizes.toDF("b", "other"), "b").groupBy("a").agg(F.sum("other").alias("others"))
    linked = classes.join(near.withColumnRenamed("a", "doc_id"), "doc_id", "left").select(F.col("doc_id").alias("class_id"), "h", "m", "sh", (F.col("n") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"))
    return sets.join(linked, ["h", "m", "sh"]).select("doc_id", "class_id", "n_links")
