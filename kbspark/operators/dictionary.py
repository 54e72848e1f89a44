"""The synonym dictionary: expansion, lemma layer, a double-array automaton over tokens, and the same matches by
an n-gram equi-join.

The automaton is built on the driver from the synonyms (the knowledge base is small next to the texts; its size is
checked), sent to the workers once, and run over texts in Arrow batches: linear in the text and its matches,
whatever the number of patterns. Texts are never shuffled.
"""

from __future__ import annotations

import gc
import pickle
import re
import zlib
from collections import defaultdict, deque
from collections.abc import Iterator
from functools import reduce
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kbspark.functions.text import lemma, ngrams
from kbspark.session import keep

TOKEN = re.compile(r"[^\W_]+(?:_[^\W_]+)*|[^\W]+")
RUN = re.compile(r"\w+")  # what tokens are cut from: each lies within one run
MAX_PATTERNS = 5_000_000
LEVELS = 8  # first tokens of a pattern whose places are listed


def expand(records: DataFrame, level: int = 2) -> DataFrame:
    """record_id and synonym: 0 the name alone; 1 case and underscores; 2 also plural and number forms."""
    name = F.col("name")
    forms = [name, F.lower(name)]
    if level >= 1:
        forms += [F.regexp_replace(F.lower(name), r"[_#\-]+", " "), F.regexp_replace(F.lower(name), r"^[a-z]_", "")]
    if level >= 2:
        forms += [F.concat(F.lower(name), F.lit("s")), F.regexp_replace(F.lower(name), r"^\d+-", "")]
    made = F.array(*forms) if level else F.array(name)
    if "synonyms" in records.columns and level:
        made = F.concat(made, F.col("synonyms"))
    cleaned = F.array_distinct(F.filter(F.transform(made, F.trim), lambda s: s != ""))
    return records.select("record_id", F.explode(cleaned).alias("synonym")).distinct()


class Automaton:
    """Aho-Corasick over token numbers, as a double array (base, check) with failure and output links.

    kind "trie" keeps plain dictionaries of children instead: the same matches, more memory.
    """

    def __init__(self, patterns: list[tuple[str, list[str]]], kind: str = "double"):
        """patterns: (id, tokens)."""
        if len(patterns) > MAX_PATTERNS:
            raise ValueError(f"{len(patterns)} patterns: split the dictionary by first token")
        self.kind, self.ids = kind, [p for p, _ in patterns]
        self.lengths = np.array([len(t) for _, t in patterns], np.int32)
        self.numbers: dict[str, int] = {}
        trie: list[dict[int, int]] = [{}]
        ends: list[list[int]] = [[]]
        # Token numbers by their place in a pattern: all, and those with which a pattern may be over.
        places: list[set[int]] = [set() for _ in range(LEVELS)]
        lasts: list[set[int]] = [set() for _ in range(LEVELS)]
        for k, (_, tokens) in enumerate(patterns):
            at = 0
            for t in tokens:
                n = self.numbers.setdefault(t, len(self.numbers) + 1)
                if n not in trie[at]:
                    trie.append({})
                    ends.append([])
                    trie[at][n] = len(trie) - 1
                at = trie[at][n]
            if tokens:
                ends[at].append(k)
                ns = [self.numbers[t] for t in tokens[:LEVELS]]
                for level, n in zip(places, ns, strict=False):
                    level.add(n)
                lasts[len(ns) - 1].add(ns[-1])
        self.places, self.lasts = ([np.fromiter(x, np.int32, len(x)) for x in xs] for xs in (places, lasts))
        fail, out = [0] * len(trie), [0] * len(trie)  # out: nearest state by failure links that ends a pattern
        queue = deque(trie[0].values())
        while queue:
            s = queue.popleft()
            for n, child in trie[s].items():
                f = fail[s]
                while f and n not in trie[f]:
                    f = fail[f]
                fail[child] = trie[f][n] if n in trie[f] and trie[f][n] != child else 0
                out[child] = fail[child] if ends[fail[child]] else out[fail[child]]
                queue.append(child)
        if kind == "double":
            self._pack(trie, fail, out, ends)
        else:
            leaf: dict[int, int] = {}  # shared, as most states are leaves
            self.trie, self.fail, self.out, self.ends = [t or leaf for t in trie], fail, out, [tuple(e) for e in ends]

    def _pack(self, trie, fail, out, ends) -> None:
        """Place each state's children at base + token number; slot numbers replace state numbers.

        The root's children take slots by token number; other states, most with one child, fill free slots.
        """
        size = len(trie) + len(self.numbers) + 2
        base, check = [-1] * (2 * size), [-1] * (2 * size)
        slot = [0] * len(trie)
        check[0], free, queue = 0, 1, deque([0])
        while queue:
            s = queue.popleft()
            kids = sorted(trie[s].items())
            if not kids:
                continue
            low, high = kids[0][0], kids[-1][0]
            b = max(free - low, 0)
            while True:
                if b + high >= len(check):
                    base += [-1] * (len(base) + high)
                    check += [-1] * (len(base) - len(check))
                if all(check[b + n] < 0 for n, _ in kids):
                    break
                b += 1
            base[slot[s]] = b
            for n, child in kids:
                check[b + n] = slot[s]
                slot[child] = b + n
                queue.append(child)
            while free < len(check) and check[free] >= 0:
                free += 1
        last = max(slot) + 1
        self.base, self.check = np.array(base[:last], np.int32), np.array(check[:last], np.int32)
        self.fail, self.out = np.zeros(last, np.int32), np.zeros(last, np.int32)
        at = np.array(slot, np.int64)
        self.fail[at], self.out[at] = at[fail], at[out]
        self.ends = {slot[s]: tuple(e) for s, e in enumerate(ends) if e}

    def bytes(self) -> int:
        if self.kind == "double":
            return int(self.base.nbytes + self.check.nbytes + self.fail.nbytes + self.out.nbytes)
        return 64 * len(self.trie) + 100 * sum(map(len, self.trie))

    def matches(self, tokens: list[str]) -> Iterator[tuple[int, int, int]]:
        """(pattern number, first token, token after the last) for all patterns that occur, by their end."""
        numbers, at, double = self.numbers, 0, self.kind == "double"
        if double:
            base, check, fail = self.base, self.check, self.fail
            size = len(check)
        for i, t in enumerate(tokens):
            n = numbers.get(t)
            if n is None:
                at = 0
                continue
            while True:
                if double:
                    b = base[at]
                    to = b + n if b >= 0 else -1
                    hit = 0 <= to < size and check[to] == at
                else:
                    to = self.trie[at].get(n, -1)
                    hit = to >= 0
                if hit:
                    at = int(to)
                    break
                if not at:
                    break
                at = int(self.fail[at] if double else self.fail[at])
            s = at
            while s:
                for k in (self.ends.get(s, ()) if double else self.ends[s]):
                    yield k, i + 1 - int(self.lengths[k]), i + 1
                s = int(self.out[s])


def tokens_of(text: str | None) -> list[tuple[str, int, int]]:
    return [(m[0].lower(), m.start(), m.end()) for m in TOKEN.finditer(text or "")]


def build(synonyms: DataFrame, kind: str = "double", lang: str | None = None) -> Automaton:
    """From record_id and synonym. Collects the synonyms, whose number is checked against MAX_PATTERNS first."""
    if synonyms.count() > MAX_PATTERNS:
        raise ValueError("too many synonyms for one automaton; shard by first token")
    rows = synonyms.select("record_id", "synonym").orderBy("record_id", "synonym").collect()
    return Automaton([(r[0], [lemma_text(t, lang) for t, _, _ in tokens_of(r[1])]) for r in rows], kind)


PART = 100_000  # patterns of one automaton among several
AT_ONCE = 5  # automata that are sent together
CHUNK = 1 << 19  # tokens that are numbered together, give or take a text
SLOTS = 1 << 22  # words share a slot by chance: then more texts are matched than need be


class Sealed(NamedTuple):
    """An automaton as it is sent, and its figures."""

    packed: bytes
    patterns: int
    size: int


def seal(a: Automaton) -> Sealed:
    return Sealed(zlib.compress(pickle.dumps(a), 1), len(a.ids), a.bytes())


def slots_of(words: list) -> np.ndarray:
    return np.fromiter((zlib.crc32(w.encode()) for w in words), np.uint32, len(words)) & np.uint32(SLOTS - 1)


class Places:
    """By the slot of a token: bits of the places in a pattern (LEVELS of them) where some pattern has it, and of those with which
    one may be over. A match begins only where the tokens that follow all have their places."""

    def __init__(self):
        self.inside, self.last, self.longest = np.zeros(SLOTS, np.uint8), np.zeros(SLOTS, np.uint8), 0

    @staticmethod
    def of(a: Automaton) -> tuple[bytes, bytes, bytes, int]:
        """What add needs of an automaton."""
        inside, last = np.zeros((2, len(a.numbers) + 1), np.uint8)
        for k in range(LEVELS):
            inside[a.places[k]] |= 1 << k
            last[a.lasts[k]] |= 1 << k
        return slots_of(list(a.numbers)).tobytes(), inside[1:].tobytes(), last[1:].tobytes(), int(a.lengths.max(initial=0))

    def add(self, slots: bytes, inside: bytes, last: bytes, longest: int) -> None:
        at = np.frombuffer(slots, np.uint32)
        np.bitwise_or.at(self.inside, at, np.frombuffer(inside, np.uint8))
        np.bitwise_or.at(self.last, at, np.frombuffer(last, np.uint8))
        self.longest = max(self.longest, longest)

    def starts(self, slots: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Places in codes, all at which a match begins among them, ascending. slots: of the words that codes number."""
        inside, last = self.inside[slots], self.last[slots]
        inside[0] = last[0] = 0  # between texts
        here = inside[codes]
        at, found = np.flatnonzero(here & 1), []
        for k in range(LEVELS):
            if k:
                at = at[here[at + k] & (1 << k) != 0]
            found.append(at[last[codes[at + k]] & (1 << k) != 0])
        return np.unique(np.concatenate(found))


def build_parts(synonyms: DataFrame, kind: str = "double", part: int = PART) -> tuple[Places, Iterator[list[Sealed]]]:
    """Automata that have all the synonyms between them, whatever their number, AT_ONCE at a time, and the places of their
    tokens. Tasks build them and the driver passes them on as bytes. Synonyms with the same first word are in one part; up
    to `part` of them, there is one part, which the driver builds."""
    parts = -(-synonyms.count() // part) or 1
    places = Places()
    if parts == 1:
        a = build(synonyms, kind)
        places.add(*Places.of(a))
        return places, iter([[seal(a)]])

    def one(key: tuple, rows: pa.Table) -> pa.Table:
        rows = rows.take(pc.sort_indices(rows, [("record_id", "ascending"), ("synonym", "ascending")], null_placement="at_start"))
        pairs = zip(rows["record_id"].to_pylist(), rows["synonym"].to_pylist(), strict=True)
        gc.disable()  # it would go through all states again and again
        try:
            a = Automaton([(i, [t for t, _, _ in tokens_of(s)]) for i, s in pairs], kind)
            made = (key[0].as_py(), *seal(a), *Places.of(a))
        finally:
            gc.enable()
        return pa.Table.from_arrays([pa.array([x]) for x in made], ["part", "packed", "patterns", "size", "slots", "inside", "last", "longest"])

    word = F.regexp_extract(F.lower("synonym"), r"[\p{L}\p{N}]+", 0)
    dealt = synonyms.select("record_id", "synonym", F.pmod(F.xxhash64(word), F.lit(parts)).alias("part")).repartition(parts, "part")
    made = keep(dealt.groupBy("part").applyInArrow(one, "part long, packed binary, patterns long, size long, slots binary, inside binary, last binary, longest long"), "automata")
    for low in range(0, parts, 10 * AT_ONCE):
        for r in made.where(F.col("part").between(low, low + 10 * AT_ONCE - 1)).select("slots", "inside", "last", "longest").collect():
            places.add(*r)

    def groups() -> Iterator[list[Sealed]]:
        for low in range(0, parts, AT_ONCE):
            some = range(low, min(low + AT_ONCE, parts))
            got = {r["part"]: Sealed(bytes(r["packed"]), r["patterns"], r["size"]) for r in made.where(F.col("part").between(some[0], some[-1])).select("part", "patterns", "size", "packed").collect()}
            yield [got.get(i) or seal(Automaton([], kind)) for i in some]

    return places, groups()


NUMBERED = "words string, slots binary, codes binary"


def _row(words: list, slots: np.ndarray, codes: np.ndarray) -> pa.RecordBatch:
    arrays = [pa.array(["\n".join(words)], pa.string()), pa.array([slots.tobytes()], pa.binary()), pa.array([codes.astype(np.int32).tobytes()], pa.binary())]
    return pa.RecordBatch.from_arrays(arrays, ["words", "slots", "codes"])


def _counter() -> defaultdict:
    """Numbers what it is asked for in the order of first sight; None is 0."""
    numbers: defaultdict = defaultdict()
    numbers.default_factory = numbers.__len__
    numbers[None]  # noqa: B018
    return numbers


def tokens(df: DataFrame, text: str) -> DataFrame:
    """The tokens that match sees in the texts, many texts to a row: words, lines of the different ones after an empty line, their
    slots (uint32 values), and codes, the lines of all tokens (int32 values, from 0) in their order, with 0 after each text."""

    def numbered(runs: defaultdict, codes: list[int]) -> pa.RecordBatch:
        words = _counter()
        own = [[0] if r is None else [words[t.lower()] for t in (TOKEN.findall(r) if "_" in r else (r,))] for r in runs]
        at = np.array(codes, np.int32)
        if len(longer := [i for i, o in enumerate(own) if len(o) > 1]):  # runs with underscores that are several tokens
            lengths = np.ones(len(own), np.int64)
            lengths[longer] = [len(own[i]) for i in longer]
            n = lengths[at]
            within = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
            at = np.repeat((np.cumsum(lengths) - lengths)[at], n) + within
        out = np.fromiter((c for o in own for c in o), np.int32)[at]
        names = ["", *list(words)[1:]]
        return _row(names, slots_of(names), out)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs, codes = _counter(), []
        for b in batches:
            for low in range(0, b.num_rows, 200):
                for t in b.column(0).slice(low, 200).to_pylist():
                    codes += map(runs.__getitem__, RUN.findall(t or ""))
                    codes.append(0)
                    if len(codes) >= CHUNK:
                        yield numbered(runs, codes)
                        runs, codes = _counter(), []
        if codes:
            yield numbered(runs, codes)

    return df.select(text).mapInArrow(run, NUMBERED)


def _read(b: pa.RecordBatch, row: int) -> tuple[list[str], np.ndarray, np.ndarray]:
    return b.column(0)[row].as_py().split("\n"), np.frombuffer(b.column(1)[row].as_buffer(), np.uint32), np.frombuffer(b.column(2)[row].as_buffer(), np.int32)


def near_matches(tokens: DataFrame, places) -> DataFrame:
    """Of numbered tokens, those that a match can be made of (Places, broadcast): pieces of texts with all their matches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in range(b.num_rows):
                words, slots, codes = _read(b, row)
                at = places.value.starts(slots, codes)
                if not len(at):
                    continue
                # Each piece goes from a start to the end of the longest pattern there; those that meet are one.
                stop = np.minimum(at + places.value.longest, len(codes))
                new = np.flatnonzero(np.append(True, at[1:] > stop[:-1]))
                begin, end = at[new], stop[np.append(new[1:] - 1, len(at) - 1)]
                n = end - begin + 1  # and 0 after each
                piece = np.repeat(begin - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
                kept = codes[np.minimum(piece, len(codes) - 1)]
                kept[np.cumsum(n) - 1] = 0
                used = np.unique(np.append(kept, 0))
                yield _row([words[c] for c in used.tolist()], slots[used], np.searchsorted(used, kept))

    return tokens.select("words", "slots", "codes").mapInArrow(run, NUMBERED)


def count_matches(tokens: DataFrame, automata) -> int:
    """How many matches the automata (a list of packed ones, broadcast) have in numbered tokens, overlaps included. A worker
    unpacks one at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = 0
            for packed in automata.value if b.num_rows else ():
                a = pickle.loads(zlib.decompress(packed))
                for row in range(b.num_rows):
                    words, _, codes = _read(b, row)
                    n += sum(1 for _ in a.matches([words[c] for c in codes.tolist()]))  # no pattern has the empty word
                del a
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])

    return tokens.select("words", "slots", "codes").mapInArrow(run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def lemma_text(word: str, lang: str | None) -> str:
    from kbspark.functions.text import ENDINGS

    if lang is None:
        return word
    for e in ENDINGS[lang]:
        if word.endswith(e) and len(word) >= len(e) + 3:
            return word[: -len(e)]
    return word


def match(df: DataFrame, key: str, text: str, automaton: Automaton, mode: str = "all", lang: str | None = None) -> DataFrame:
    """key, record_id, first and last (tokens), start and stop (characters of the original text).

    mode all: every occurrence, overlaps included; longest: leftmost and longest, no overlaps.
    """
    shared = df.sparkSession.sparkContext.broadcast(automaton)
    kind = dict(df.dtypes)[key]
    id_type = pa.string() if automaton.ids and isinstance(automaton.ids[0], str) else pa.int64()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = shared.value
        for b in batches:
            out: list[tuple] = []
            for row, t in enumerate(b.column(1).to_pylist()):
                toks = tokens_of(t)
                found = list(a.matches([lemma_text(w, lang) for w, _, _ in toks]))
                if mode == "longest":
                    kept, free = [], 0
                    for k, s, e in sorted(found, key=lambda m: (m[1], -m[2])):
                        if s >= free:
                            kept.append((k, s, e))
                            free = e
                    found = kept
                out += [(row, a.ids[k], s, e, toks[s][1], toks[e - 1][2]) for k, s, e in found]
            cols = list(zip(*out, strict=True)) if out else [[]] * 6
            yield pa.RecordBatch.from_arrays(
                [b.column(0).take(pa.array(cols[0], pa.int32())), pa.array(cols[1], id_type), *(pa.array(c, pa.int32()) for c in cols[2:])],
                ["k", "record_id", "first", "last", "start", "stop"],
            )

    made = df.select(key, text).mapInArrow(run, f"k {kind}, record_id {'string' if id_type == pa.string() else 'long'}, first int, last int, start int, stop int")
    return made.withColumnRenamed("k", key)


def match_ngrams(df: DataFrame, key: str, text: str, synonyms: DataFrame, max_len: int = 8, lang: str | None = None) -> DataFrame:
    """The same matches as an equi-join of token n-grams with the synonyms: key, record_id, first, last.

    A synonym of more than max_len tokens is cut into parts of max_len (the last may overlap the one before); it is
    there where all its parts are, at their places. Without synonyms there are no rows.
    """
    fold = (lambda w: lemma(w, lang)) if lang else (lambda w: w)
    toks = F.transform(F.regexp_extract_all(F.lower(text), F.lit(TOKEN.pattern.replace(r"[^\W_]", r"[\p{L}\p{N}]").replace(r"[^\W]", r"[\p{L}\p{N}_]")), 0), fold)
    cells = df.select(key, F.explode(F.array(toks)).alias("ws"))
    pats = synonyms.select("record_id", "synonym", F.explode(F.array(F.transform(F.regexp_extract_all(F.lower("synonym"), F.lit(r"[\p{L}\p{N}]+(?:_[\p{L}\p{N}]+)*|[\p{L}\p{N}_]+"), 0), fold))).alias("ws"))
    pats = pats.withColumn("n", F.size("ws")).where("n > 0")
    gram_at = lambda n: cells.select(key, F.posexplode(ngrams(F.col("ws"), n)).alias("first", "g"))
    found = []
    for n in sorted(r[0] for r in pats.where(F.col("n") <= max_len).select("n").distinct().collect()):  # at most max_len numbers
        mine = pats.where(F.col("n") == n).select("record_id", F.array_join("ws", " ").alias("g"))
        found.append(gram_at(n).join(mine, "g").select(key, "record_id", "first", (F.col("first") + n).alias("last")))
    longer = pats.where(F.col("n") > max_len)
    if not longer.isEmpty():
        last = F.col("n") - max_len
        places = F.array_distinct(F.concat(F.sequence(F.lit(0), last, F.lit(max_len)), F.array(last)))
        parts = longer.select("record_id", "synonym", "n", F.size(places).alias("parts"), F.explode(F.transform(places, lambda i: F.struct(i.alias("off"), F.array_join(F.slice("ws", i + 1, max_len), " ").alias("g")))).alias("x"))
        hit = gram_at(max_len).join(parts.select("record_id", "synonym", "n", "parts", "x.off", "x.g"), "g").withColumn("first", F.col("first") - F.col("off")).where("first >= 0")
        whole = hit.groupBy(key, "record_id", "synonym", "n", "parts", "first").agg(F.count_distinct("off").alias("got")).where("got = parts")
        found.append(whole.select(key, "record_id", "first", (F.col("first") + F.col("n")).alias("last")))
    if not found:
        none = [F.col(key), F.lit(None).cast(dict(synonyms.dtypes)["record_id"]).alias("record_id"), F.lit(0).alias("first"), F.lit(0).alias("last")]
        return df.select(*none).where(F.lit(False))
    return reduce(DataFrame.union, found)


def longest_only(hits: DataFrame, key: str) -> DataFrame:
    """Hits that no longer hit covers, by windows: the longest for each start, then those not inside an earlier one."""
    w = Window.partitionBy(key, "first").orderBy(F.desc("last"), "record_id")
    best = hits.withColumn("r", F.row_number().over(w)).where("r = 1").drop("r")
    before = Window.partitionBy(key).orderBy("first").rowsBetween(Window.unboundedPreceding, -1)
    return best.withColumn("reach", F.max("last").over(before)).where(F.col("reach").isNull() | (F.col("last") > F.col("reach"))).drop("reach")
