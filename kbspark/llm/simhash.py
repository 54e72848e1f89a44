"""SimHash near-duplicates, found with pivot distance tables.

Fingerprints of equal value are one item from the start, so copies cost nothing later. The table holds each
fingerprint's Hamming distances to reference fingerprints (pivots) of two sorts:

- Block pivots: zero, and one for each block of two bits, ones there and zero elsewhere. The distances to zero and to a
  block's pivot give the number of ones in the block, so these 33 coordinates are kept as 32 such numbers. Fingerprints
  at most 3 bits apart have at most 3 different numbers: they agree in one of four parts of 8 blocks, and of the 24
  others in one of four parts of 6. So the pairs to compare meet under one of 16 keys of 14 coordinates.
- Wide pivots, at random. By the triangle inequality no coordinate of a pair at most 3 bits apart differs by more than 3;
  a pair with a larger difference in any is discarded. 7 coordinates are compared at once in one long.

What survives is verified bit by bit. Keys that too many fingerprints share are split on the coordinates not yet
used, by the same argument; groups that agree in nearly all of them are told apart by pivots of one bit. So no link is
lost, and no group's pairs are all listed. (Keys of wide pivots alone can't propose pairs: a coordinate's bands let
about half of all pairs pass and double the rows, so rows would grow faster than pairs fall.)

Defined cases: a null text, or one without words, has fingerprint 0 and is linked like any other; texts of
one or two words have one shingle; a component's id is its smallest non-null doc_id; rows repeated in the
input are repeated in the output.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kbspark.llm.common import cut, slices
from kbspark.operators.components import components


def fingerprint(text: str | None, size: int = 3) -> int:
    """The 64-bit fingerprint of a text's word shingles, unsigned."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) <= size:
        shingles = [b" ".join(words)]
    else:
        shingles = map(b" ".join, zip(*(words[i:] for i in range(size)), strict=False))
    hashes = np.fromiter(map(lambda s: xxhash.xxh64_intdigest(s, 42), shingles), ">u8")
    ones = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 65_536):
        ones += np.unpackbits(hashes[i : i + 65_536].view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, keep: list[str], text: str = "text", size: int = 3) -> DataFrame:
    """The columns in keep and fp, the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            fps = np.array([fingerprint(t, size) for t in b.column(b.num_columns - 1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(fps, pa.int64())], [*b.schema.names[:-1], "fp"])

    rows = docs.select(*keep, F.col(text).alias("__text"))
    return rows.mapInArrow(run, T.StructType([*rows.schema.fields[:-1], T.StructField("fp", T.LongType())]))


FULL = (1 << 64) - 1
EVEN = 0x5555555555555555
LANES, LANE = 7, 8  # coordinates in a long, and bits for each: none needs the sign


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def pivots(n: int, seed: int = 11) -> list[int]:
    """Reference fingerprints, spread at random, as signed longs."""
    return [int(x) for x in np.random.default_rng(seed).integers(-(1 << 63), (1 << 63) - 1, n)]


def distance(fp: Column, ref: int) -> Column:
    return F.bit_count(fp.bitwiseXOR(F.lit(ref))).cast("long")


def block_pivots() -> list[int]:
    """Zero, then ones in one block of two bits each, from the lowest."""
    return [0, *(signed(3 << 2 * i) for i in range(32))]


def block_coordinates(fp: Column) -> Column:
    """(2 + distance to zero - distance to the block's pivot) / 2 for all 32 blocks, two bits each: the ones in a block."""
    odd = F.shiftrightunsigned(fp, 1)
    one = fp.bitwiseXOR(odd).bitwiseAND(F.lit(EVEN))
    return one.bitwiseOR(F.shiftleft(fp.bitwiseAND(odd).bitwiseAND(F.lit(EVEN)), 1))


def wide_coordinates(fp: Column, refs: list[int]) -> list[Column]:
    """Distances to the references, LANES of them in a long."""
    parts = [refs[i : i + LANES] for i in range(0, len(refs), LANES)]
    return [reduce(Column.bitwiseOR, (F.shiftleft(distance(fp, r), LANE * i) for i, r in enumerate(p))) for p in parts]


def within(a: Column, b: Column, k: int) -> Column:
    """Whether no coordinate of two packed longs differs by more than k (at most 60)."""
    all_ = lambda x: F.lit(sum(x << LANE * i for i in range(LANES)))
    top, more = all_(0x80), all_(k)
    above = lambda x, y: x.bitwiseOR(top) - y + more  # noqa: E731  (a lane keeps its top bit where x >= y - k)
    return above(a, b).bitwiseAND(above(b, a)).bitwiseAND(top) == top


def parts_of(mask: int, width: int, n: int) -> list[int]:
    """The blocks of mask, of `width` bits each, in n parts of about equal size, as masks."""
    block = (1 << width) - 1
    blocks = [block << i for i in range(0, 64, width) if mask >> i & 1]
    return [sum(blocks[i * len(blocks) // n : (i + 1) * len(blocks) // n]) for i in range(n)]


def meetings(fps: DataFrame, k: int, crowd: int, bits_left: int = 6) -> list[DataFrame]:
    """Frames of mask, key and fp: any two fingerprints at most k bits apart share mask and key in one of them, and at
    most `crowd` (or 2 ** bits_left) fingerprints share them."""
    made: list[DataFrame] = []

    def search(fps: DataFrame, coordinates: Column, width: int) -> DataFrame | None:
        """Groups by keys of the coordinates; gives back the fingerprints of groups that can't be split further."""
        # A key is its mask (the coordinates that agree) and the values under it; the mask tells the unused ones.
        masks = [a | b for a in parts_of(FULL, width, k + 1) for b in parts_of(FULL & ~a, width, k + 1)]
        each = F.array(*(F.struct(F.lit(signed(m)).alias("mask"), F.col("c").bitwiseAND(F.lit(signed(m))).alias("key")) for m in masks))
        level = fps.select("fp", coordinates.alias("c")).select("fp", "c", F.inline(each).alias("mask", "key"))
        while True:
            sizes = level.groupBy("mask", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
            shared = cut(level.join(sizes, ["mask", "key"]))
            made.append(shared.where(F.col("n") <= crowd).select("mask", "key", "fp"))
            crowded = shared.where(F.col("n") > crowd)
            if crowded.isEmpty():
                return None
            of = sorted({r[0] & FULL for r in crowded.select("mask").distinct().collect()})  # as many as there are masks
            if 64 - max(m.bit_count() for m in of) <= bits_left:
                return crowded
            finer = {m: [m | p for p in parts_of(FULL & ~m, width, k + 1)] for m in of}
            table = F.create_map(*(c for m in of for c in (F.lit(signed(m)), F.array(*(F.lit(signed(x)) for x in finer[m])))))
            level = crowded.select("fp", "c", F.explode(F.element_at(table, F.col("mask"))).alias("mask"))
            level = level.select("fp", "c", "mask", F.col("c").bitwiseAND(F.col("mask")).alias("key")).distinct()

    rest = search(fps, block_coordinates(F.col("fp")), 2)
    if rest is not None:
        # Pivots of one bit: these coordinates are the bits themselves, so the last groups are small by themselves.
        rest = search(rest.select("fp").distinct(), F.col("fp"), 1)
        if rest is not None:
            made.append(rest.select("mask", "key", "fp"))
    return made


def proposals(fps: DataFrame, k: int = 3, n_pivots: int = 14, crowd: int = 48) -> DataFrame:
    """a < b (fingerprints that meet) and passes: whether the wide pivots let the pair through."""
    refs, pairs = pivots(n_pivots), []
    for met in meetings(fps, k, crowd):
        side = lambda name, p: met.select("mask", "key", F.col("fp").alias(name), *(c.alias(f"{p}{i}") for i, c in enumerate(wide_coordinates(F.col("fp"), refs))))  # noqa: B023, E731
        passes = reduce(Column.__and__, (within(F.col(f"x{i}"), F.col(f"y{i}"), k) for i in range(-(-n_pivots // LANES))))
        pairs.append(side("a", "x").join(side("b", "y"), ["mask", "key"]).where("a < b").select("a", "b", passes.alias("passes")))
    return reduce(DataFrame.union, pairs)


def links(fps: DataFrame, k: int = 3, n_pivots: int = 14, crowd: int = 48) -> DataFrame:
    """a < b (longs): all pairs of distinct fingerprints (column fp) at most k bits apart."""
    found = proposals(fps, k, n_pivots, crowd).where("passes").select("a", "b")
    return found.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= k).distinct()


def work(fps: DataFrame, k: int = 3, n_pivots: int = 14, crowd: int = 48) -> DataFrame:
    """One row: met, discarded (by the wide pivots), verified, and linked (pairs, each counted wherever it meets)."""
    near = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= k
    return proposals(fps, k, n_pivots, crowd).agg(
        F.count(F.lit(1)).alias("met"), F.count_if(~F.col("passes")).alias("discarded"), F.count_if(F.col("passes")).alias("verified"), F.count_if(F.col("passes") & near).alias("linked")
    )


def groups(rows: DataFrame) -> DataFrame:
    """fp, root (a number of the group) and component_id of all distinct fingerprints of rows (columns doc_id, fp)."""
    items = cut(rows.groupBy("fp").agg(F.min("doc_id").alias("least")))
    found = components(links(items).select(F.col("a").alias("u"), F.col("b").alias("v")))
    rooted = items.join(found.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    return rooted.join(least, "root").select("fp", "root", "component_id")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint (16 hex digits) and component_id of all documents."""
    rows = cut(fingerprints(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), ["doc_id"]))
    out = rows.join(groups(rows), "fp")
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
