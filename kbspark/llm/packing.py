"""Packing documents into sequences by the configuration linear program over the length histogram.

Lengths are grouped into classes; a configuration says how many items of each class share a sequence. The
program (fewest sequences that cover every class) is solved by multiplicative weights: each class has a
price that falls as it is covered, and each round a knapsack dynamic program finds the configuration worth
most at these prices. Rounded down, configurations become groups of like sequences; what is left over goes,
longest first, where it fits best. The shortest pieces, a fifth of all tokens, are set aside before the program: they
close its groups and fill what is left free, as is usual for such schemes. All this works on counts by length, so it is the same work for any number
of documents. Documents are then dealt to the slots by their rank among pieces of the same length; ranks come
from salted groups, so that one length may hold any share of the rows.

Defined cases: a null or empty text is the single token of the document's end; only documents longer than a
sequence are cut; repeated rows are packed as often as they occur; an empty table gives no rows.
"""

from __future__ import annotations

import gc
import os
import unicodedata
import zlib
from bisect import bisect_left, bisect_right, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kbspark.llm.common import cut, give_back

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


class Encoder:
    """Ids of whole texts, put together from those of their parts.

    The tokenizer never joins text across a blank, nor across the pre-token borders of its own pattern, so ids
    are remembered by blank-separated chunk and by pre-token. New pre-tokens are encoded many at a time: each
    ends with a token that carries the end-of-word mark, which tells them apart again.
    """

    def __init__(self, path: str, chunks: int = 250_000, pretokens: int = 350_000, longest: int = 64):
        import regex
        from tokenizers import Tokenizer

        self.tok, self.limits, self.longest = Tokenizer.from_file(path), (chunks, pretokens), longest
        self.chunks: dict[str, bytes] = {"": b""}
        self.pretokens: dict[str, bytes] = {}
        # Fixed value: the pre-token pattern of the tokenizer's file.
        self.split = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+").findall
        vocab = self.tok.get_vocab(with_added_tokens=True)
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True

    def alone(self, chunk: str) -> bytes:
        return np.array(self.tok.encode(chunk, add_special_tokens=False).ids, "<u4").tobytes()

    def plain(self, chunk: str) -> list[str] | None:
        """The chunk's pre-tokens, or None if it has what only the tokenizer itself should deal with."""
        if "<|" in chunk:
            return None
        low = chunk
        if not chunk.isascii():
            low = unicodedata.normalize("NFC", chunk)
            if "Σ" in low or len(low.lower()) != len(low):  # lower case that depends on neighbours or grows
                return None
        low = low.lower()
        if low.isalpha():
            return [low]
        if low[-1] in ".,!?:;" and low[:-1].isalpha():
            return [low[:-1], low[-1]]
        return self.split(low)

    def learn(self, new: list[str]) -> dict[str, bytes]:
        """The ids of new pre-tokens."""
        learnt: dict[str, bytes] = {}
        for i in range(0, len(new), 512):
            some = new[i : i + 512]
            ids = np.array(self.tok.encode(" ".join(some), add_special_tokens=False).ids, "<u4")
            cuts = np.flatnonzero(self.ends[ids]) + 1
            if len(cuts) == len(some):
                raw, low = ids.tobytes(), 0
                for w, high in zip(some, (4 * cuts).tolist(), strict=True):
                    learnt[w] = raw[low:high]
                    low = high
            else:
                for w in some:
                    learnt[w] = self.alone(w)
        return learnt

    @staticmethod
    def cut(text: str) -> list[str]:
        """The text at its blanks; the four separators that only Python takes for blanks stay in."""
        if any(c in text for c in "\x1c\x1d\x1e\x1f"):
            return text.replace("\n", " ").replace("\t", " ").split(" ")
        return text.split()

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit numbers."""
        rows = [self.cut(t) if t else [] for t in texts]
        known, pre = self.chunks, self.pretokens
        found = [list(map(known.get, parts)) for parts in rows]
        gaps = [[i for i, v in enumerate(values) if v is None] for values in found]
        if new := {parts[i] for parts, gap in zip(rows, gaps, strict=True) for i in gap}:
            cut = {w: self.plain(w) for w in new}
            fresh = self.learn(list({p for parts in cut.values() if parts for p in parts if p not in pre}))
            made = {}
            for w, parts in cut.items():
                made[w] = self.alone(w) if parts is None else b"".join([pre[p] if p in pre else fresh[p] for p in parts])
            for parts, values, gap in zip(rows, found, gaps, strict=True):
                for i in gap:
                    values[i] = made[parts[i]]
            # Full memories stay as they are: what is frequent came early. Long blobs are never kept, so bytes are bounded too.
            if len(known) < self.limits[0]:
                known.update((w, ids) for w, ids in made.items() if len(w) <= self.longest)
            if len(pre) < self.limits[1]:
                pre.update((w, ids) for w, ids in fresh.items() if len(w) <= self.longest)
        return list(map(b"".join, found))


#: Encoders by file, of the worker process that holds this module: they live from one task to the next.
ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    if path not in ENCODERS:
        ENCODERS[path] = Encoder(path)
    return ENCODERS[path]


def tokenize(docs: DataFrame, tokenizer: str, end_id: int = 0, max_len: int = 2048, with_ids: bool = False) -> DataFrame:
    """Pieces of all documents: doc_id, piece, start, length, ids_crc32 (and ids, if with_ids, as bytes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from kbspark.llm.packing import encoder

        gc.disable()  # lists of words come and go by the million, without cycles
        encode, tail, step = encoder(tokenizer).encode, np.uint32(end_id).tobytes(), 4 * max_len
        for whole in batches:
            for low in range(0, whole.num_rows, 128):
                b = whole.slice(low, 128)
                out: tuple[list, ...] = ([], [], [], [], [], [])
                for i, ids in enumerate(encode(b.column(1).to_pylist())):
                    ids += tail
                    for piece, at in enumerate(range(0, len(ids), step)):
                        cell = ids[at : at + step]
                        for column, v in zip(out, (i, piece, at // 4, len(cell) // 4, zlib.crc32(cell), cell if with_ids else None), strict=True):
                            column.append(v)
                columns = [b.column(0).take(pa.array(out[0], pa.int32())), pa.array(out[1], pa.int32()), *(pa.array(c, pa.int64()) for c in out[2:5])]
                if with_ids:
                    columns.append(pa.array(out[5], pa.binary()))
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "piece", "start", "length", "ids_crc32", "ids"][: len(columns)])
            give_back()
        gc.enable()

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, PIECES + (", ids binary" if with_ids else ""))


def classes(sizes: np.ndarray, counts: np.ndarray, at_most: int) -> np.ndarray:
    """The class of each size: runs of neighbouring sizes of about equal tokens in all, at most so many."""
    if len(sizes) <= at_most:
        return np.arange(len(sizes))
    mass = np.cumsum(sizes * counts) / float((sizes * counts).sum())
    cut_at = np.minimum((mass * at_most * 0.999).astype(int), at_most - 1)
    return np.unique(cut_at, return_inverse=True)[1]


def best_configuration(width: np.ndarray, price: np.ndarray, cap: int) -> tuple[np.ndarray, float]:
    """Unbounded knapsack by dynamic programming over the capacity: counts by class and their worth."""
    best, took = np.zeros(cap + 1), np.full(cap + 1, -1)
    order = np.argsort(width)
    w, p = width[order], price[order]
    upto = np.searchsorted(w, np.arange(cap + 1), side="right")
    for c in range(int(w[0]), cap + 1):
        k = upto[c]
        value = best[c - w[:k]] + p[:k]
        i = int(value.argmax())
        if value[i] > best[c - 1]:
            best[c], took[c] = value[i], i
        else:
            best[c] = best[c - 1]
    counts, c = np.zeros(len(width), int), cap
    while c > 0:
        if took[c] < 0:
            c -= 1
        else:
            counts[order[took[c]]] += 1
            c -= int(w[took[c]])
    return counts, float(best[cap])


def solve(width: np.ndarray, demand: np.ndarray, cap: int, eps: float = 0.15, rounds: int = 1500) -> tuple[list[tuple[np.ndarray, float]], float]:
    """A fractional cover of all classes by configurations, and a lower bound on the sequences needed.

    Each round takes as much of the priced configuration as raises its scarcest class by the share eps of its
    demand; so there are at most classes / eps rounds. Any prices give a bound: their total over the best
    configuration's worth.
    """
    covered, cover, bound = np.zeros(len(width)), {}, 0.0
    for _ in range(rounds):
        open_ = covered < demand - 1e-9
        if not open_.any():
            break
        price = width * np.exp(-2.0 * covered / demand)
        a, worth = best_configuration(width, np.where(open_, price, 0.0), cap)
        bound = max(bound, float((price * demand * open_).sum()) / worth)
        used = a > 0
        amount = float((np.maximum(eps * demand[used], np.minimum(1.0, demand[used])) / a[used]).min())
        amount = min(amount, float((np.maximum(demand[used] - covered[used], 1e-9) / a[used]).max()))
        key = a.tobytes()
        cover[key] = (a, cover.get(key, (a, 0.0))[1] + amount)
        covered += a * amount
    return list(cover.values()), bound


class Plan:
    """Groups of like sequences: per length, runs of ranks with the first sequence, the items per sequence
    of that length, and the place of the first of them. Without the program, all is best fit."""

    def __init__(self, histogram: dict[int, int], cap: int = 2048, at_most: int = 160, aside: float = 0.2, tight: float = 0.999, program: bool = True):
        self.cap = cap
        self.left = {s: n for s, n in sorted(histogram.items()) if n}
        self.lengths = list(self.left)  # in order
        self.groups: list[list] = []  # [pattern {length: items}, sequences, slack]
        total = sum(s * n for s, n in self.left.items())
        self.bound = -(-total // cap)
        if cap in self.left:
            self.add({cap: 1}, self.left[cap])
        if program:
            self.follow(at_most, aside, tight)
        self.fit_rest()

    def follow(self, at_most: int, aside: float, tight: float) -> None:
        """Solve the program for all but the shortest pieces (`aside` of all tokens) and round it down."""
        sizes = np.array(list(self.left), int)
        counts = np.array([self.left[s] for s in sizes.tolist()], int)
        large = np.cumsum(sizes * counts) > aside * (sizes * counts).sum()
        sizes, counts = sizes[large], counts[large]
        if len(sizes):
            of = classes(sizes, counts, at_most)
            width = np.array([sizes[of == k].max() for k in range(of.max() + 1)])
            demand = np.array([counts[of == k].sum() for k in range(of.max() + 1)], float)
            self.members = [sizes[of == k][::-1].tolist() for k in range(of.max() + 1)]
            found, self.lp_bound = solve(width, demand, self.cap)
            full = [(a, x) for a, x in found if a @ width >= tight * self.cap]  # the last rounds only have a few classes to cover
            for a, x in sorted(full, key=lambda f: -f[1]):
                self.fill(a, int(x))

    def add(self, pattern: dict[int, int], times: int) -> None:
        for s, k in pattern.items():
            self.left[s] -= k * times
            if not self.left[s]:
                del self.left[s]
                del self.lengths[bisect_left(self.lengths, s)]
        self.groups.append([pattern, times, self.cap - sum(s * k for s, k in pattern.items())])

    def fill(self, a: np.ndarray, times: int) -> None:
        """Turn a configuration of classes into groups of true lengths, as long as there are items. Classes stand for
        their widest member, so the last item is the longest of any class that still fits: groups have no gaps then."""
        wanted = [k for k in np.flatnonzero(a)[::-1].tolist() for _ in range(int(a[k]))]
        while times > 0:
            pattern: dict[int, int] = {}
            room = self.cap
            more = lambda s: self.left.get(s, 0) > pattern.get(s, 0)
            for k in wanted[:-1]:
                s = next((s for s in self.members[k] if more(s)), None)
                if s is None:
                    return
                pattern[s] = pattern.get(s, 0) + 1
                room -= s
            at = bisect_right(self.lengths, room) - 1
            while at >= 0 and not more(self.lengths[at]):
                at -= 1
            if at < 0 or self.lengths[at] < room:
                return
            pattern[room] = pattern.get(room, 0) + 1
            n = min(times, *(self.left[s] // k for s, k in pattern.items()))
            self.add(pattern, n)
            times -= n

    def fit_rest(self) -> None:
        """Longest first into the fullest sequence that still takes it; a new sequence if none does."""
        by_slack: dict[int, list[int]] = {}
        for i, g in enumerate(self.groups):
            by_slack.setdefault(g[2], []).append(i)
        slacks = sorted(by_slack)
        for s in sorted(self.left, reverse=True):
            n = self.left[s]
            while n:
                at = bisect_left(slacks, s)
                if at == len(slacks):
                    k = min(self.cap // s, n)
                    made = [{s: k}, n // k, self.cap - s * k]
                    n -= k * made[1]
                    self.groups.append(made)
                    i = len(self.groups) - 1
                else:
                    slack = slacks[at]
                    i = by_slack[slack].pop()
                    if not by_slack[slack]:
                        del by_slack[slack], slacks[at]
                    pattern, times, _ = self.groups[i]
                    k = min(slack // s, n)
                    put = min(times, n // k)
                    if put < times:
                        self.groups.append([dict(pattern), times - put, slack])
                        self.note(by_slack, slacks, slack, len(self.groups) - 1)
                    self.groups[i] = [pattern | {s: pattern.get(s, 0) + k}, put, slack - s * k]
                    n -= k * put
                self.note(by_slack, slacks, self.groups[i][2], i)
        self.left = {}

    @staticmethod
    def note(by_slack: dict, slacks: list, slack: int, i: int) -> None:
        if slack not in by_slack:
            insort(slacks, slack)
        by_slack.setdefault(slack, []).append(i)

    def sequences(self) -> int:
        return sum(g[1] for g in self.groups)

    def runs(self) -> dict[int, tuple[np.ndarray, ...]]:
        out: dict[int, list[tuple[int, int, int, int]]] = {}
        rank: dict[int, int] = {}
        first = 0
        for pattern, times, _ in self.groups:
            at = 0
            for s in sorted(pattern, reverse=True):
                k = pattern[s]
                out.setdefault(s, []).append((rank.get(s, 0), first, k, at))
                rank[s] = rank.get(s, 0) + k * times
                at += s * k
            first += times
        return {s: tuple(np.array(c, np.int64) for c in zip(*v, strict=True)) for s, v in out.items()}


def best_plan(histogram: dict[int, int], cap: int = 2048) -> Plan:
    """The program's plan, or that of best fit alone where it takes fewer sequences."""
    return min(Plan(histogram, cap), Plan(histogram, cap, program=False), key=Plan.sequences)


def pack(pieces: DataFrame, max_len: int = 2048) -> tuple[DataFrame, Plan]:
    """Pieces (columns of PIECES, materialised) with sequence_id and offset, and the plan they follow."""
    salts = max(32, pieces.count() // 2_000_000)
    salted = pieces.withColumn("__salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)))
    tally = cut(salted.groupBy("length", "__salt").agg(F.count(F.lit(1)).alias("__n")))
    histogram = {int(r[0]): int(r[1]) for r in tally.groupBy("length").agg(F.sum("__n")).collect()}  # max_len rows at most
    plan = best_plan(histogram, max_len)
    before = Window.partitionBy("length").orderBy("__salt").rowsBetween(Window.unboundedPreceding, -1)
    starts = tally.select("length", "__salt", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__first"))
    inside = Window.partitionBy("length", "__salt").orderBy("doc_id", "piece", "start", "ids_crc32")
    ranks = salted.withColumn("__row", F.row_number().over(inside) - 1).join(starts, ["length", "__salt"])
    ranks = ranks.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("__first") + F.col("__row")).alias("__rank"))
    runs = plan.runs()

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            length, rank = (np.asarray(b.column(i).to_numpy(zero_copy_only=False), np.int64) for i in (3, 5))
            sequence, offset = np.empty(len(rank), np.int64), np.empty(len(rank), np.int64)
            for s in np.unique(length).tolist():
                rows = np.flatnonzero(length == s)
                low, first, each, at = runs[s]
                i = np.searchsorted(low, rank[rows], side="right") - 1
                inside = rank[rows] - low[i]
                sequence[rows] = first[i] + inside // each[i]
                offset[rows] = at[i] + inside % each[i] * s
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(sequence), pa.array(offset)], [*b.schema.names[:5], "sequence_id", "offset"])

    return ranks.mapInArrow(place, PIECES + ", sequence_id long, offset long"), plan


def pack_documents(docs: DataFrame, tokenizer: str, max_len: int = 2048) -> DataFrame:
    return pack(cut(tokenize(docs, tokenizer, max_len=max_len)), max_len)[0]
