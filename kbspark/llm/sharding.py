"""Shards along a Hilbert curve over document metadata. DataFrame functions only.

Several dimensions (language and source by the rank of their value among all distinct values, size on a logarithmic
scale from the smallest to the largest) are quantised to whole numbers; documents are
sorted by the place of their cell on the Hilbert curve, equal texts beside each other, and the sorted run is
cut into shards of equal counts. Neighbours on the curve are neighbours in every dimension, so each shard's
(and each file's) minimum and maximum of every dimension stay close, and readers can skip it.

Defined cases: nulls are level 0 in their dimension; a null text has size 1; ties in everything but doc_id
are ordered by doc_id, repeated rows arbitrarily; an empty table gives no rows; with fewer rows than shards
the last shards are empty.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kbspark.llm.common import if_few, ranked, unused


def rotate(x: Column, k: Column, d: int) -> Column:
    """x, d bits wide, rotated right by k places (0 <= k < d)."""
    at = [F.shiftright(x, i).bitwiseOR(F.shiftleft(x, d - i)).bitwiseAND(F.lit((1 << d) - 1)) for i in range(d)]
    return F.element_at(F.array(*at), (k + 1).cast("int"))


def hilbert_index(levels: list[Column], bits: int) -> Column:
    """The place on the Hilbert curve of the cell with these levels (whole numbers under 2 ** bits).

    Goes down one level of the grid at a time and keeps the sub-cube's entry corner and direction; what
    depends on the corner number alone is looked up in arrays of 2 ** dimensions literals.
    """
    d = len(levels)
    if d == 1:
        return levels[0].cast("long")
    n = 1 << d
    turn = lambda x, k: ((x << k) | (x >> (d - k))) & (n - 1)
    gray = lambda i: i ^ (i >> 1)
    place = [0] * n
    for i in range(n):
        place[gray(i)] = i
    trailing = lambda i: (~i & (i + 1)).bit_length() - 1
    entry = [0 if i == 0 else gray(2 * ((i - 1) // 2)) for i in range(n)]
    direction = [0 if i == 0 else (trailing(i - 1) if i % 2 == 0 else trailing(i)) % d for i in range(n)]
    look = lambda values, i: F.element_at(F.array(*(F.lit(v) for v in values)), (i + 1).cast("int"))
    # All d rotations of an entry corner, by corner and amount: one look-up in place of a variable shift.
    turned = [turn(e, k) for e in entry for k in range(d)]

    state = F.struct(F.lit(0).cast("long").alias("h"), F.lit(0).alias("e"), F.lit(0).alias("k"))
    corners = F.array(*(sum((F.shiftright(x.cast("int"), b).bitwiseAND(F.lit(1)) * (1 << i) for i, x in enumerate(levels)), F.lit(0)) for b in reversed(range(bits))))

    def step(s: Column, corner: Column) -> Column:
        local = rotate(corner.bitwiseXOR(s["e"]), (s["k"] + 1) % d, d)
        w = look(place, local)
        return F.struct(
            (s["h"] * n + w).cast("long").alias("h"),
            s["e"].bitwiseXOR(look(turned, w * d + (s["k"] + 1) % d)).alias("e"),
            ((s["k"] + look(direction, w) + 1) % d).alias("k"),
        )

    return F.aggregate(corners, state, step, lambda s: s["h"])


LEVEL_ROWS = 1_000_000  # distinct values (two numbers each) that are broadcast at most; beyond, the join is a shuffle


def with_level(rows: DataFrame, column: str, level: str, bits: int) -> DataFrame:
    """rows with a level of column by the rank of its value among all distinct values, spread over 1 to 2 ** bits - 1; nulls 0.

    With more values than levels, neighbours in the order of strings share one.
    """
    value, key = unused("value", rows), unused("key", rows)
    distinct, n, _ = ranked(rows.select(F.col(column).alias(value)).where(F.col(column).isNotNull()).distinct(), [value])
    top = (1 << bits) - 1
    place = (1 + F.floor(F.col("__rank") * top / max(n, 1))).cast("int")
    levels = distinct.select(F.xxhash64(value).alias(key), place.alias(level)).dropDuplicates([key])
    made = rows.withColumn(value, F.xxhash64(column)).join(if_few(levels, LEVEL_ROWS), F.col(value) == F.col(key), "left")
    return made.drop(value, key).withColumn(level, F.when(F.col(column).isNull(), 0).otherwise(F.col(level)))


def size_of(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 1


def size_level(size: Column, low: int, high: int, bits: int) -> Column:
    """Sizes on a logarithmic scale from the smallest to the largest."""
    span = max(math.log2(max(high, 1)) - math.log2(max(low, 1)), 1e-9)
    level = F.floor((F.log2(size.cast("double")) - math.log2(max(low, 1))) * ((1 << bits) - 1) / span)
    return F.greatest(F.lit(0), F.least(level, F.lit((1 << bits) - 1))).cast("int")


def hilbert_shards(docs: DataFrame, shards: int = 8, bits: int = 9) -> DataFrame:
    """doc_id, size, text_crc32, hilbert, rank, shard and slot of all documents; counts differ by one at most."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        size_of(F.col("text")).alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.col("lang").alias("lang"),
        F.col("source").alias("source"),
    )
    low, high = rows.agg(F.min("size"), F.max("size")).first()
    rows = with_level(with_level(rows, "lang", "by_lang", bits), "source", "by_source", bits)
    at = [F.col("by_lang"), F.col("by_source"), size_level(F.col("size"), low or 1, high or 1, bits)]
    rows = rows.select("doc_id", "size", "text_crc32", hilbert_index(at, bits).alias("hilbert"))
    placed, n, _ = ranked(rows, ["hilbert", "size", "text_crc32", "doc_id"])
    each, more = divmod(n, shards)
    rank, longer = F.col("__rank"), more * (each + 1)
    first = F.when(rank < longer, F.floor(rank / (each + 1))).otherwise(more + F.floor((rank - longer) / max(each, 1)))
    start = F.when(F.col("shard") <= more, F.col("shard") * (each + 1)).otherwise(longer + (F.col("shard") - more) * each)
    out = placed.withColumn("shard", first.cast("int"))
    return out.select("doc_id", "size", "text_crc32", "hilbert", rank.alias("rank"), "shard", (rank - start).cast("long").alias("slot"))


def write_shards(sharded: DataFrame, docs: DataFrame, path: str, name: str = "shard", file_rows: int = 100_000) -> None:
    """The documents as Parquet, a folder a shard (called name=0 and so on), in files of neighbours along the curve.

    docs keeps its columns, so name may not be one of them; doc_id must tell its rows apart.
    """
    if name in docs.columns:
        raise ValueError(f"documents have a column {name}: choose another name")
    d, slot, file = (unused(x, docs) for x in ("d", "slot", "file"))
    at = sharded.select(F.col("doc_id").alias(d), F.col("shard").alias(name), F.col("slot").alias(slot))
    placed = docs.join(at, F.col("doc_id").cast("long") == F.col(d)).withColumn(file, F.floor(F.col(slot) / file_rows))
    dealt = placed.repartition(name, file).sortWithinPartitions(name, file, slot)
    dealt.drop(d, slot, file).write.partitionBy(name).parquet(path)
