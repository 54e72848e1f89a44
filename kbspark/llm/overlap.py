"""Near copies by the exact Jaccard similarity of word shingles, found without losing a pair.

A text's set of five-word shingles is held as 64-bit hashes. Texts of equal sets are one item. SimHash fingerprints
of these sets, linked with pivot tables (`simhash`), propose the first pairs, each item with the first of its fingerprint
and each fingerprint with the least one linked; those that reach the similarity connect most near copies at a cost that is linear in the items. Fingerprints miss pairs
that are more than a few bits apart, and at a similarity of 0.8 most are; so the items not connected yet are joined by prefix:

Two sets of similarity 4/5 or more share one of their first n - ceil(4n/5) + 1 shingles in any order that is the same for
all, so items meet under these only. The order puts shingles that a sample of texts often has last, by
count, and others by hash; what the sample holds changes the work, never the pairs. Pairs under one shingle are
dropped by bounds that no true pair fails (sizes, the number of prefix shingles in common, parity bits of the whole
sets), and the rest are verified on the whole sets.

Items of groups under one shingle of more than `crowd` are compared with a few of their own first, those that have
least of their own: what copies with changes were made from. Then only items that aren't connected yet are compared, so
a dense group's pairs are not all listed; in such groups the join itself drops pairs by parity bits, as many as the texts'
sizes ask for, so that texts too far from each other aren't listed either, however long they are.

Defined cases: null texts and texts without words are one item; texts of fewer than five words have one shingle.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kbspark.llm import simhash
from kbspark.llm.common import cut, if_few, rest, slices
from kbspark.operators.components import components

# Words of a shingle, the similarity as a fraction, longs of parity bits, as many as crowded groups are first held
# against, and at most so many for long texts, so that a row stays small.
WORDS, NUM, DEN, PARITY, FOLDED, WIDEST = 5, 4, 5, 16, 8, 512
KNOWN: dict[bytes, int] = {}  # hashes of words met lately
MOST_KNOWN = 100_000
TURNS = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], np.uint64)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


def shingles(text: str | None) -> np.ndarray:
    """The distinct shingles of a text as sorted hashes."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if len(KNOWN) > MOST_KNOWN:
        KNOWN.clear()
    for w in set(words).difference(KNOWN):
        KNOWN[w] = xxhash.xxh64_intdigest(w, 7)
    h = np.fromiter(map(KNOWN.__getitem__, words), np.uint64, len(words))
    if len(h) < WORDS:  # padded by the number of words, so that no longer text's shingle is meant
        h = np.concatenate([h, np.full(WORDS - len(h), len(h), np.uint64)])
    m = len(h) - WORDS + 1
    total = np.zeros(m, np.uint64)
    for k in range(WORDS):
        total += mixed(h[k : k + m] * TURNS[k] + TURNS[WORDS - 1 - k])
    return np.unique(mixed(total))


def prefix_length(n: int) -> int:
    return n - (NUM * n + DEN - 1) // DEN + 1


def parity(sh: np.ndarray, longs: int = PARITY) -> np.ndarray:
    """For each of 64 * longs cells, whether an odd number of shingles is in it; two sets differ in as many shingles at least as these differ in bits."""
    odd = np.bincount((sh >> np.uint64(20)).astype(np.int64) & (64 * longs - 1), minlength=64 * longs) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def wide_parity(sh: np.ndarray) -> np.ndarray:
    """Parity bits of four to eight cells a shingle, a power of two of longs; none where PARITY longs are as many."""
    longs = min(WIDEST, 1 << max(0, (len(sh) - 1) // 16).bit_length())
    return parity(sh, longs) if longs > PARITY else np.zeros(0, np.int64)


def frequent(docs: DataFrame, texts: int = 5_000, least: int = 3, most: int = 200_000) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that many texts of a sample have, sorted, and in how many: only for the order."""
    share = min(1.0, texts / max(1, docs.count()))
    some = docs.where(F.pmod(F.xxhash64("doc_id", "key", F.lit("order")), F.lit(1_000_000)) < int(1_000_000 * share) + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            sets = [shingles(t) for t in b.column(0).to_pylist()]
            found, n = np.unique(np.concatenate(sets), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), pa.array(n)], ["sh", "n"])

    counted = some.select("text").mapInArrow(run, "sh long, n long").groupBy("sh").agg(F.sum("n").alias("n")).where(F.col("n") >= least)
    top = counted.orderBy(F.desc("n"), "sh").limit(most).collect()
    sh, n = np.array([r[0] for r in top], np.int64).view(np.uint64), np.array([r[1] for r in top], np.int64)
    by = np.argsort(sh)
    return sh[by], n[by]


def fingerprint(sh: np.ndarray) -> int:
    """A bit is 1 if more than half the shingles have it."""
    ones = np.zeros(64, np.int64)
    for i in range(0, len(sh), 65_536):
        ones += np.unpackbits(sh[i : i + 65_536].view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(sh)).view(np.int64)[0])


def marked(docs: DataFrame) -> DataFrame:
    """doc_id, key, item (a hash of the shingle set), n (its size), fp, prefix, bits and wide of all rows (columns doc_id, key, text)."""
    often, times = frequent(docs)

    def first(sh: np.ndarray) -> np.ndarray:
        p = prefix_length(len(sh))
        if not len(often):
            return sh[:p]
        at = np.minimum(np.searchsorted(often, sh), len(often) - 1)
        n = np.where(often[at] == sh, times[at], 0)
        return sh[np.argsort(n, kind="stable")[:p]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for b in slices(batches):
            sets = [shingles(t) for t in b.column(2).to_pylist()]
            item = np.array([xxhash.xxh64_intdigest(s.tobytes(), 3) for s in sets], np.uint64).view(np.int64)
            firsts = [first(s).view(np.int64) for s in sets]
            listed = lambda xs: pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, xs)]), pa.int32()), pa.array(np.concatenate(xs)))
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(item), pa.array(np.fromiter(map(len, sets), np.int32)), pa.array([fingerprint(s) for s in sets], pa.int64()), listed(firsts), listed([parity(s) for s in sets]), listed([wide_parity(s) for s in sets])],
                ["doc_id", "key", "item", "n", "fp", "prefix", "bits", "wide"],
            )

    return docs.select("doc_id", "key", "text").mapInArrow(run, "doc_id long, key long, item long, n int, fp long, prefix array<long>, bits array<long>, wide array<long>")


def whole_sets(docs: DataFrame) -> DataFrame:
    """item and sh, the whole shingle set, of docs (columns item, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            sets = [shingles(t).view(np.int64) for t in b.column(1).to_pylist()]
            ends = pa.array(np.cumsum([0, *map(len, sets)]), pa.int32())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(ends, pa.array(np.concatenate(sets)))], ["item", "sh"])

    return docs.select("item", "text").mapInArrow(run, T.StructType([T.StructField("item", T.LongType()), T.StructField("sh", T.ArrayType(T.LongType()))]))


def sizes_allow(a: str, b: str) -> Column:
    n, m = F.col(f"{a}n"), F.col(f"{b}n")
    return DEN * F.least(n, m) >= NUM * F.greatest(n, m)


def places_allow(a: str, b: str) -> Column:
    """No pair of the similarity or more fails this in the first shingle that both prefixes have."""
    f = lambda side, name: F.col(f"{side}{name}")
    return (NUM + DEN) * F.least(f(a, "n") - f(a, "pos"), f(b, "n") - f(b, "pos")) >= NUM * (f(a, "n") + f(b, "n"))


def counts_allow(a: str, b: str) -> Column:
    """The similarity asks for 4/9 of both sizes in common. Of the set whose prefix ends first in the order, all common
    shingles in the prefix are in the other's prefix too; so c, the shingles in both prefixes, and what is after the
    longer set's prefix must reach that."""
    n, m = F.col(f"{a}n"), F.col(f"{b}n")
    after = F.floor((NUM * F.greatest(n, m) + DEN - 1) / DEN) - 1
    return (NUM + DEN) * (F.col("c") + after) >= NUM * (n + m)


def folded(bits: Column) -> Column:
    """Parity bits of fewer cells: each holds the shingles of PARITY / FOLDED of the former, so it is odd if an odd number of these is."""
    return F.array(*(reduce(Column.bitwiseXOR, (bits[k] for k in range(i, PARITY, FOLDED))) for i in range(FOLDED)))


def parities_allow(u: str, v: str, longs: int = PARITY) -> Column:
    """No such pair's parity bits differ in more places than its sets may."""
    differ = sum((F.bit_count(F.col(f"{u}bits")[i].bitwiseXOR(F.col(f"{v}bits")[i])) for i in range(1, longs)), F.bit_count(F.col(f"{u}bits")[0].bitwiseXOR(F.col(f"{v}bits")[0])))
    return (NUM + DEN) * differ <= (DEN - NUM) * (F.col(f"{u}n") + F.col(f"{v}n"))


def fine_allow(u: str, v: str) -> Column:
    """As parities_allow, by all bits that both have: sizes that are allowed are a power of two apart at most, and the longer bits are folded once."""
    x, y = F.col(f"{u}fine"), F.col(f"{v}fine")
    halves = lambda z: (F.slice(z, 1, F.shiftright(F.size(z), 1)), F.slice(z, F.shiftright(F.size(z), 1) + 1, F.shiftright(F.size(z), 1)))
    fit = lambda z, w: F.when(F.size(z) > F.size(w), F.zip_with(*halves(z), Column.bitwiseXOR)).otherwise(z)
    differ = F.aggregate(F.zip_with(fit(x, y), fit(y, x), lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), Column.__add__)
    return (NUM + DEN) * differ <= (DEN - NUM) * (F.col(f"{u}n") + F.col(f"{v}n"))


def meet(left: DataFrame, right: DataFrame) -> DataFrame:
    """Pairs under one shingle; rows that carry parity bits are held against them here, before a row is made."""
    kept = [c for c in ("item", "n", "pos", "root", "bits", "fine") if c in right.columns]
    a, b = (df.select("sh", *(F.col(c).alias(s + c) for c in kept)) for s, df in (("a_", left), ("b_", right)))
    allowed = sizes_allow("a_", "b_") & (F.col("a_root") != F.col("b_root"))
    if "bits" in kept:
        allowed &= parities_allow("a_", "b_", FOLDED) & fine_allow("a_", "b_")  # the dearest last
    return a.join(b, "sh").where(allowed)


FEW = 1_000_000  # items' numbers that are broadcast at most; beyond, the join is a shuffle
LINKS = 200_000  # pairs whose groups the driver finds at most; beyond, rounds of joins do
CENTRES = 10_000  # centres that are broadcast at most, each with its parity bits


def roots(found: DataFrame) -> DataFrame:
    """item and root (a number of the group) of all items on the pairs found."""
    return if_few(components(found, few=LINKS).withColumnRenamed("node", "item"), 2 * LINKS)


def links(rows: DataFrame, docs: DataFrame, crowd: int = 32, centres: int = 2) -> DataFrame:
    """u, v: pairs of items of the similarity or more, as many as connect all that are connected by such pairs.
    rows are from marked(docs), kept."""
    who = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key")).alias("who")
    items = cut(rows.groupBy("item").agg(F.any_value("n").alias("n"), F.any_value("fp").alias("fp"), F.any_value("bits").alias("bits"), who))

    def verified(found: DataFrame) -> DataFrame:
        """The pairs that reach the similarity: first by their parity bits, then by the whole sets of those left."""
        known = items.select("item", "n", "bits")
        for side in ("u", "v"):
            found = found.join(known.toDF(side, f"{side}_n", f"{side}_bits"), side)
        found = cut(found.where(parities_allow("u_", "v_")).select("u", "v").distinct())
        needed = found.select(F.explode(F.array("u", "v")).alias("item")).distinct()
        who = cut(items.join(needed, "item").select("item", F.col("who.doc_id").alias("d"), F.col("who.key").alias("k")))
        texts = docs.join(if_few(who, FEW), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("key") == F.col("k"))).select("item", "text")
        rest(docs.sparkSession)
        sets = cut(whole_sets(texts))  # an item whose row is repeated is there as often
        x, y = sets.select(F.col("item").alias("u"), F.col("sh").alias("su")), sets.select(F.col("item").alias("v"), F.col("sh").alias("sv"))
        same = (NUM + DEN) * F.size(F.array_intersect("su", "sv"))
        return cut(found.join(x, "u").join(y, "v").where(same >= NUM * (F.size("su") + F.size("sv"))).select("u", "v").distinct())

    def rooted(df: DataFrame, found: DataFrame) -> DataFrame:
        return df.join(roots(found), "item", "left").withColumn("root", F.coalesce("root", "item"))

    # Each item proposes the first of its fingerprint, and this the first of the least fingerprint linked with its own.
    firsts = cut(items.groupBy("fp").agg(F.min("item").alias("first")))
    near = simhash.links(firsts)
    least = near.union(near.select("b", "a")).groupBy("a").agg(F.min("b").alias("b"))
    across = least.join(firsts.toDF("a", "x"), "a").join(firsts.toDF("b", "y"), "b").select("x", "y")
    proposed = items.join(firsts, "fp").where("item <> first").select("item", "first").union(across)
    found = verified(proposed.select(F.least("item", "first").alias("u"), F.greatest("item", "first").alias("v")).distinct())

    # All columns pass the one exchange that both the count and the join read.
    firsts = rows.groupBy("item").agg(F.any_value("n").alias("n"), F.any_value("prefix").alias("prefix"))
    placed = firsts.select("item", "n", F.posexplode("prefix").alias("pos", "sh")).repartition("sh")
    sizes = placed.groupBy("sh").agg(F.count(F.lit(1)).alias("m"), *(F.max(c).alias(f"max_{c}") for c in ("item", "n", "pos"))).where("m > 1 AND max_item IS NOT NULL AND max_n >= 0 AND max_pos >= 0")
    shared = cut(rooted(placed.join(sizes, "sh").select("sh", "item", "n", "pos", "m"), found))

    few, many = shared.where(F.col("m") <= crowd), shared.where(F.col("m") > crowd)
    crowded = not many.isEmpty()
    if crowded:
        # Centres have the largest share of crowded shingles: a copy's changes are shingles of its own, and these come first
        # in its prefix. Then by a hash of the item, so that the same items are centres under many shingles.
        share = many.groupBy("item").agg((F.count(F.lit(1)) / F.any_value("n")).alias("share"))
        wide = rows.groupBy("item").agg(F.any_value("wide").alias("wide"), F.any_value("bits").alias("bits")).join(share, "item")
        fine = F.when(F.size("wide") > 0, F.col("wide")).otherwise(F.col("bits")).alias("fine")
        many = cut(many.join(wide.select("item", "share", folded(F.col("bits")).alias("bits"), fine), "item"))
        rank = F.row_number().over(Window.partitionBy("sh").orderBy(F.desc("share"), F.xxhash64("item"), "item"))
        middle = if_few(cut(many.withColumn("r", rank).where(F.col("r") <= centres)), CENTRES)
        star = meet(middle, many).where(places_allow("a_", "b_")).select(F.least("a_item", "b_item").alias("u"), F.greatest("a_item", "b_item").alias("v")).distinct()
        found = cut(found.union(verified(star)))
        few, many = cut(rooted(few.drop("root"), found)), cut(rooted(many.drop("root", "share"), found))
    # How many prefix shingles two items share is counted over all shingles they meet under. A pair that parity bits drop in
    # crowded groups is no link, so it may be counted short elsewhere.
    met = [meet(x, x).where("a_item < b_item").select("a_item", "b_item", "a_n", "b_n") for x in ([few, many] if crowded else [few])]
    met = reduce(DataFrame.union, met).groupBy(F.col("a_item").alias("u"), F.col("b_item").alias("v"))
    pairs = met.agg(F.count(F.lit(1)).alias("c"), F.max("a_n").alias("a_n"), F.max("b_n").alias("b_n")).where(counts_allow("a_", "b_"))
    return found.union(verified(pairs.select("u", "v")))


def groups(rows: DataFrame, docs: DataFrame) -> DataFrame:
    """item and root (a number of the group) of all items of rows, which are from marked(docs), kept."""
    return rows.select("item").distinct().join(roots(links(rows, docs)), "item", "left").select("item", F.coalesce("root", "item").alias("root"))
