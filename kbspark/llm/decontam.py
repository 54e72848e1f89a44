"""Benchmark decontamination by a prefix-filtered set join. DataFrame functions only.

A benchmark item's windows (runs of `size` words; the whole item if it is shorter) are sets of word shingles.
A window that occurs in a document has all its shingles there, so it is enough to look for one: the prefix
is the window's rarest shingle, by the counts of all documents. Documents' shingles are joined with the
benchmark's on a hash; those that are some window's prefix propose a start; the start must leave room for
the window (positional and length bounds), and the words from there are compared with the window's one by one. Up to
there windows travel as numbers, and only texts with a proposed start are read again, and split once.

Defined cases: a null text has no words, and neither has an item of punctuation alone, which never occurs;
documents that repeat a doc_id are judged by doc_id and text; a very long text is one row at a time; windows
that several items share count for each; an empty table on either side gives no hit.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kbspark.llm.common import UPPER, cut, if_few

# The ASCII characters that never belong to a word once A-Z is lower-cased.
APART = "".join(map(chr, [*range(0x00, 0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x80)]))
BROADCAST_ROWS = 1_000_000  # of benchmark shingles, windows or document numbers (no texts): beyond, the join is a shuffle


def words_of(text: Column) -> Column:
    """A-Z lower-cased and everything that isn't a word made a blank in one pass, then cut at blanks."""
    plain = F.translate(F.coalesce(text, F.lit("")), UPPER + APART, UPPER.lower() + " " * len(APART))
    return F.array_remove(F.split(plain, " "), "")


def shingle_hashes(words: Column, n: int) -> Column:
    """A hash for each run of n words."""
    last = F.size(words) - n + 1
    return F.when(last > 0, F.transform(F.sequence(F.lit(1), last), lambda i: F.xxhash64(*(F.element_at(words, i + k) for k in range(n))))).otherwise(F.array().cast("array<bigint>"))


def windows_of(items: DataFrame, size: int) -> tuple[DataFrame, DataFrame]:
    """Distinct windows (wid, a number, and w, the words), and the items that have them (wid, item_id)."""
    words = items.select("item_id", words_of(F.col("text")).alias("ws")).where(F.size("ws") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.size("ws") - size + 1, F.lit(1)))
    each = words.select("item_id", F.explode(F.transform(starts, lambda i: F.slice("ws", i, size))).alias("w")).distinct()
    wins = cut(each.select("w").distinct().withColumn("wid", F.monotonically_increasing_id()))
    return wins, cut(each.join(wins, "w").select("wid", "item_id"))


def covered(spans: Column) -> Column:
    """How many places an array of (s, len) structs covers, overlaps once."""
    start = F.struct(F.lit(0).cast("long").alias("end"), F.lit(0).cast("long").alias("n"))

    def one(acc: Column, c: Column) -> Column:
        stop = (c["s"] + c["len"]).cast("long")
        return F.struct(F.greatest(acc["end"], stop).alias("end"), (acc["n"] + F.greatest(stop - F.greatest(acc["end"], c["s"].cast("long")), F.lit(0).cast("long"))).alias("n"))

    return F.aggregate(F.array_sort(spans), start, one, lambda acc: acc["n"])


def contaminated(docs: DataFrame, items: DataFrame, size: int = 10, shingle: int = 3) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated and key (the text's hash) of all documents."""
    wins, owners = windows_of(items, size)
    # The shingles of a window, with their places; a window of fewer words is one shingle.
    n_of = F.least(F.size("w"), F.lit(shingle))
    lengths = sorted(r[0] for r in wins.select(n_of.alias("n")).distinct().collect()) or [shingle]  # at most `shingle` of them
    per = [wins.where(n_of == n).select("wid", F.size("w").alias("len"), F.posexplode(shingle_hashes(F.col("w"), n)).alias("at", "h")).withColumn("n", F.lit(n)) for n in lengths]
    tokens = cut(reduce(DataFrame.union, per))
    known = tokens.select("n", "h").distinct()
    small = tokens.count() <= BROADCAST_ROWS  # numbers only, and at least as many as windows

    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("key"))
    cells = keyed.select("doc_id", "key", words_of(F.col("text")).alias("ws"))
    spread = []
    for i, n in enumerate(lengths):
        # Place 0 of the first holds the number of words, so that one pass over the texts serves for both.
        head = F.size("ws").cast("long")
        each = cells.select("doc_id", "key", F.posexplode(F.concat(F.array(head), shingle_hashes(F.col("ws"), n))).alias("pos", "h"))
        mine = known.where(F.col("n") == n).select("h", F.lit(True).alias("met"))
        each = each.join(F.broadcast(mine) if small else mine, "h", "left").where((F.col("pos") > 0) & F.col("met") | (F.col("pos") == 0) & F.lit(i == 0))
        spread.append(each.select("doc_id", "key", F.lit(n).alias("n"), (F.col("pos") - 1).alias("pos"), "h"))
    met = cut(reduce(DataFrame.union, spread))
    base, met = met.where("pos < 0").select("doc_id", "key", F.col("h").alias("n_words")), met.where("pos >= 0")

    rarity = met.groupBy("n", "h").agg(F.count(F.lit(1)).alias("often"))
    # A shingle that no document has rules its windows out.
    rated = tokens.join(rarity, ["n", "h"], "left").withColumn("often", F.coalesce("often", F.lit(0)))
    first = Window.partitionBy("wid").orderBy("often", "h", "at")
    prefix = rated.withColumn("r", F.row_number().over(first)).where("r = 1 and often > 0").select("n", "h", "at", "len", "wid")
    proposed = met.join(F.broadcast(prefix) if small else prefix, ["n", "h"])
    start = F.col("pos") - F.col("at")
    found = cut(proposed.where(start >= 0).groupBy("doc_id", "key").agg(F.collect_set(F.struct(start.alias("s"), "len", "wid")).alias("cands")))

    same = F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("key") == F.col("k"))
    there = found.select(F.col("doc_id").alias("d"), F.col("key").alias("k"), "cands")
    some = keyed.join(if_few(there.select("d", "k"), BROADCAST_ROWS), same, "left_semi").dropDuplicates(["doc_id", "key"])
    # Exploding an array of one splits each text once, before its candidates are cut out of it.
    split = some.join(there, same).select("doc_id", "key", "cands", F.explode(F.array(words_of(F.col("text")))).alias("ws"))
    at = lambda c: F.struct(c["s"].alias("s"), c["len"].alias("len"), c["wid"].alias("wid"), F.slice(F.col("ws"), c["s"] + 1, c["len"]).alias("piece"))
    room = F.filter("cands", lambda c: c["s"] + c["len"] <= F.size("ws"))
    pieces = split.select("doc_id", "key", F.inline(F.transform(room, at)))
    hits = cut(pieces.join(F.broadcast(wins) if small else wins, "wid").where(F.col("piece") == F.col("w")).select("doc_id", "key", "s", "len", "wid"))
    places = hits.groupBy("doc_id", "key").agg(covered(F.collect_set(F.struct("s", "len"))).alias("n_hit"))
    owned = hits.select("doc_id", "key", "wid").distinct().join(F.broadcast(owners) if owners.count() <= BROADCAST_ROWS else owners, "wid").select("doc_id", "key", F.col("item_id").cast("string").alias("item")).distinct()
    named = owned.groupBy("doc_id", "key").agg(F.array_sort(F.collect_list("item")).alias("item_ids"))
    d, k = F.col("doc_id").alias("d"), F.col("key").alias("k")
    hits = places.select(d, k, "n_hit").join(named.select(d.alias("d2"), k.alias("k2"), "item_ids"), F.col("d").eqNullSafe(F.col("d2")) & (F.col("k") == F.col("k2")))

    out = base.join(hits, same, "left")
    items_of = F.coalesce("item_ids", F.array().cast("array<string>"))
    return out.select(
        "doc_id",
        "n_words",
        F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"),
        F.size(items_of).cast("long").alias("n_items"),
        F.sha2(F.array_join(items_of, ",").cast("binary"), 256).alias("items_sha256"),
        F.coalesce(F.col("n_hit") > 0, F.lit(False)).alias("contaminated"),
        "key",
    )
