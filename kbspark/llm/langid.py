"""Language identification with hyperdimensional profiles.

Every letter has a random vector of +1 and -1 drawn from its code point. An n-gram's vector is the product
of its letters' vectors, each rotated by its place; a text's vector is the sum over its n-grams, and a
language's prototype the sum over the unit-length profiles of its training texts. A text gets the language
of the prototype with the largest cosine.

Defined cases: a null text, or one without a letter, is `und` with score 0, and so is every text when no row
can be learnt from. Case, digits and punctuation never count; words are set apart by one blank letter, so a
one-letter text still has an n-gram. Ties go to the language first in alphabetical order. Rows repeated in
the input are repeated in the output. Only the columns named are read, so extra columns never clash.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kbspark.llm.common import slices

UND = "und"
WORD = re.compile(r"[^\W\d_]+")
BITS = 21  # of a code point
MASK = (1 << BITS) - 1


class Space:
    """N-gram hypervectors, made on demand and kept up to a bound."""

    def __init__(self, dim: int, n: int, seed: int, keep: int = 65_536):
        self.dim, self.n, self.seed, self.keep = dim, n, seed, keep
        self.letters: dict[int, np.ndarray] = {}
        self.vectors = np.empty((keep, dim), np.int8)  # filled from the top; keys are kept sorted beside it
        self.clear()

    def clear(self) -> None:
        self.keys, self.at, self.used = np.empty(0, np.int64), np.empty(0, np.int64), 0

    def letter(self, code: int) -> np.ndarray:
        if code not in self.letters:
            bits = np.random.default_rng([self.seed, code]).integers(0, 2, self.dim, dtype=np.int8)
            self.letters[code] = bits * 2 - 1
        return self.letters[code]

    def grams(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """The distinct n-grams of a text, as integers, and how often each occurs."""
        words = WORD.findall((text or "").lower())
        if not words:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        padded = " " + " ".join(words) + " "
        codes = np.frombuffer(padded.encode("utf-32-le"), np.uint32).astype(np.int64)
        if len(codes) < self.n:
            codes = np.pad(codes, (0, self.n - len(codes)), constant_values=32)
        key = codes[: len(codes) - self.n + 1].copy()
        for i in range(1, self.n):
            key = (key << BITS) | codes[i : len(codes) - self.n + 1 + i]
        return np.unique(key, return_counts=True)

    def rows(self, keys: np.ndarray) -> np.ndarray:
        """Places in self.vectors of the sorted keys (fewer than are kept)."""
        i = np.searchsorted(self.keys, keys)
        known = (i < len(self.keys)) & (self.keys[np.minimum(i, len(self.keys) - 1)] == keys) if len(self.keys) else np.zeros(len(keys), bool)
        if not known.all():
            if self.used + len(keys) > self.keep:
                self.clear()
                known[:] = False
            new = keys[~known]
            made = self.vectors[self.used : self.used + len(new)]
            made[:] = 1
            for place in range(self.n):
                codes, where = np.unique((new >> (BITS * (self.n - 1 - place))) & MASK, return_inverse=True)
                turned = np.stack([np.roll(self.letter(int(c)), self.n - 1 - place) for c in codes])
                made *= turned[where]
            both = np.concatenate([self.keys, new])
            order = np.argsort(both, kind="stable")
            self.keys, self.at = both[order], np.concatenate([self.at, np.arange(self.used, self.used + len(new))])[order]
            self.used += len(new)
            i = np.searchsorted(self.keys, keys)
        return self.at[i]

    def take(self, keys: np.ndarray) -> np.ndarray:
        at = self.rows(keys)
        return self.vectors[at]

    def bundle(self, keys: np.ndarray, counts: np.ndarray) -> np.ndarray:
        total = np.zeros(self.dim, np.float64)
        for i in range(0, len(keys), 2048):  # a long text has many n-grams
            part = self.take(keys[i : i + 2048]).astype(np.float32)
            total += counts[i : i + 2048].astype(np.float32) @ part
        return total


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def fit(docs: DataFrame, text: str = "text", lang: str = "lang", dim: int = 1024, n: int = 3, seed: int = 7) -> dict[str, np.ndarray]:
    """Prototypes by language, learnt from the rows given (a language per row; null ones are left out).

    Each task adds up whole-number profiles, so the sum doesn't depend on how the rows are dealt out. What
    comes to the driver is dim numbers a language.
    """

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        space, sums = Space(dim, n, seed), {}
        weights: dict[str, dict[int, int]] = {}
        for b in slices(batches):
            for t, g in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                keys, counts = space.grams(t)
                if not len(keys):
                    continue
                unit = np.rint(counts * (1e4 / np.sqrt((counts.astype(float) ** 2).sum()))).astype(np.int64)
                own = weights.setdefault(g, {})
                for k, v in zip(keys.tolist(), unit.tolist(), strict=True):
                    own[k] = own.get(k, 0) + v
                if len(own) > 100_000:
                    sums[g] = sums.get(g, 0) + total(space, weights.pop(g))
        for g, own in weights.items():
            sums[g] = sums.get(g, 0) + total(space, own)
        for g, v in sums.items():
            yield pa.RecordBatch.from_pydict({"lang": [g] * dim, "dim": np.arange(dim, dtype=np.int32), "v": v}, pa.schema([("lang", pa.string()), ("dim", pa.int32()), ("v", pa.int64())]))

    def total(space: Space, own: dict[int, int]) -> np.ndarray:
        keys = np.fromiter(own.keys(), np.int64, len(own))
        order = np.argsort(keys)
        keys, w, out = keys[order], np.fromiter(own.values(), np.int64, len(own))[order], np.zeros(dim, np.int64)
        for i in range(0, len(keys), 4096):
            out += w[i : i + 4096] @ space.take(keys[i : i + 4096]).astype(np.int64)
        return out

    rows = docs.where(F.col(text).isNotNull() & F.col(lang).isNotNull()).select(F.col(text), F.col(lang))
    parts = rows.mapInArrow(partial, "lang string, dim int, v long").groupBy("lang", "dim").agg(F.sum("v").alias("v"))
    out: dict[str, np.ndarray] = {}
    for r in parts.groupBy("lang").agg(F.sort_array(F.collect_list(F.struct("dim", "v"))).alias("vs")).collect():
        out[r["lang"]] = np.array([x["v"] for x in r["vs"]], np.float64)
    return dict(sorted(out.items()))


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], keep: list[str], text: str = "text", dim: int = 1024, n: int = 3, seed: int = 7) -> DataFrame:
    """The columns in keep, lang_pred and score: the cosine with the best prototype, at least 0.

    The text travels once, whether it is kept or not.
    """
    sent = list(keep) if text in keep else [*keep, text]
    at, n_kept = sent.index(text), len(keep)
    names = sorted(prototypes)
    matrix = np.stack([prototypes[g] / (np.linalg.norm(prototypes[g]) or 1) for g in names]) if names else np.zeros((0, dim))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        space = Space(dim, n, seed)
        for b in slices(batches):
            pred, best = [], []
            for t in b.column(at).to_pylist():
                keys, counts = space.grams(t)
                if len(keys) and names:
                    v = space.bundle(keys, counts)
                    cos = np.round(matrix @ v / (np.linalg.norm(v) or 1), 6)
                    i = int(cos.argmax())
                    pred.append(names[i])
                    best.append(float(min(1.0, max(0.0, cos[i]))))
                else:
                    pred.append(UND)
                    best.append(0.0)
            yield pa.RecordBatch.from_arrays([*b.columns[:n_kept], pa.array(pred, pa.string()), pa.array(best, pa.float64())], [*b.schema.names[:n_kept], "lang_pred", "score"])

    rows = docs.select(*sent)
    return rows.mapInArrow(score, T.StructType([*rows.schema.fields[:n_kept], T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())]))


def identify(docs: DataFrame, max_train: int = 200_000, dim: int = 1024) -> DataFrame:
    """doc_id, held_out, lang_pred and score of all documents, learnt from those not held out.

    max_train bounds the training sample: beyond it a fixed share of doc_ids by hash is learnt from.
    """
    rows = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text", "lang")
    train = rows.where(~F.col("held_out") & F.col("lang").isNotNull())
    n = train.count()
    if n > max_train:
        train = train.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(1_000_000 * max_train / n))
    return predict(rows, fit(train, dim=dim), ["doc_id", "held_out"], dim=dim)
