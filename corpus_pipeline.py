"""From raw documents to packed sequences: language, near-duplicates, benchmark passages, personal data, packing.

Each stage takes (spark, docs, sf_dir), and all but the last return the columns of docs. run() writes what a stage
returns as Parquet in the shared folder and reads it again, so a lost executor costs one stage at most.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kbspark.llm import decontam, langid, overlap, packing, pii
from kbspark.llm.common import cut, if_few, rest, table, unused
from kbspark.llm.queries import DEMO_KEY, tokenizer_path
from kbspark.session import shared_folder

MIN_SCORE = 0.05  # a text less like every language than this is rejected
FEW = 1_000_000  # documents' numbers that are broadcast at most


def text_key() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit("")))


def matching(docs: DataFrame, marks: DataFrame, how: str) -> DataFrame:
    """docs semi- or anti-joined with marks (doc_id and key, a hash of the text), whatever columns docs has."""
    d, k = unused("d", docs), unused("k", docs)
    return docs.join(marks.toDF(d, k), F.col("doc_id").cast("long").eqNullSafe(F.col(d)) & (text_key() == F.col(k)), how)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose language can be told; learns from those that say theirs."""
    # Under names of their own, so that no column of docs can clash with what is added.
    train = docs.where(~langid.held_out(F.col("doc_id")) & F.col("lang").isNotNull())
    keep = [F.col(c).alias(f"__c{i}") for i, c in enumerate(docs.columns)]
    judged = langid.predict(docs.select(*keep), langid.fit(train), [f"__c{i}" for i in range(len(docs.columns))], text=f"__c{docs.columns.index('text')}")
    kept = judged.where((F.col("lang_pred") != langid.UND) & (F.col("score") >= MIN_SCORE))
    return kept.select(*(F.col(f"__c{i}").alias(c) for i, c in enumerate(docs.columns)))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near-duplicates, linked from a Jaccard similarity of 0.8 of their five-word
    shingles: that of the smallest doc_id, nulls last, then by a hash of the text. A row that is there twice is kept
    once; different documents of one doc_id are judged apart."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("key"), "text")
    rest(spark)
    marked = cut(overlap.marked(rows))
    place = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key")
    found = cut(marked.select(place.alias("w"), "item").join(overlap.groups(marked, rows), "item").select("w", "root"))
    first = found.groupBy("root").agg(F.min("w").alias("first"))
    others = cut(found.join(first, "root").where("w <> first").select("w.doc_id", "w.key").distinct())
    kept = matching(docs, if_few(others, FEW), "left_anti")
    repeated = marked.groupBy("doc_id", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id", "key")
    if repeated.isEmpty():
        return kept
    # Only the rows that are there twice are dealt by text again.
    repeated = if_few(cut(repeated), FEW)
    return matching(kept, repeated, "left_anti").union(matching(kept, repeated, "left_semi").dropDuplicates(["doc_id", "text"]))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark window."""
    judged = decontam.contaminated(docs.select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
    bad = cut(judged.where("contaminated").select("doc_id", "key").distinct())
    return matching(docs, if_few(bad, FEW), "left_anti")


def pseudonymise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Puts pseudonyms in place of personal data; n_chars follows the text."""
    done = pii.pseudonymise(docs, DEMO_KEY)
    return done.select(*(F.length("text").cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col(c) for c in docs.columns))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id and offset of every piece."""
    rest(spark)
    return packing.pack_documents(docs, tokenizer_path())


STAGES = [("language_id", language), ("near_dedup", near_dedup), ("decontamination", decontaminate), ("pii", pseudonymise), ("packing", pack)]
ORACLE_SQL = None  # tokens, fingerprints and the packing program are beyond SQL; tests hold it against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for i, (name, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(path := f"{folder}/{i}_{name}")
        docs = spark.read.parquet(path)
    return docs
