"""Quality rules as weak supervision.

Every rule votes good (1), bad (-1) or abstains (0). Expectation-maximisation over the counts of vote patterns
(their number depends on the rules, not on the corpus) estimates how often each rule votes either way on good and
on bad texts, and how many texts are good; a document is kept if the posterior probability that it is good reaches a
threshold. So a bad vote of a rule that often errs is outweighed by the good votes of others, and one of a rule that
hardly ever errs isn't. Base failures are never kept.

Defined cases: a null text has no words and fails; texts without words never divide by 0; an empty table
gives no rows; repeated rows get the same verdict; a very long text is counted whole.
"""

from __future__ import annotations

from collections.abc import Iterator
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kbspark.llm.common import BLANKS, cut, slices

# The characters counted as symbols.
SYMBOLS = "#*$%&|<>"
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_caps", "n_stops", "n_tails", "n_stutters"]


LONG = 20_000  # words; longer texts are counted by arrays of numbers


def repeated_words(words: list[bytes], window: int) -> int:
    """Words in windows of words that are found twice or more."""
    grams = list(zip(*(words[i:] for i in range(window)), strict=False))
    if len(set(grams)) == len(grams):
        return 0
    seen: dict[tuple, int] = {}
    for g in grams:
        seen[g] = seen.get(g, 0) + 1
    repeated = upto = 0  # words before upto are counted
    for i, g in enumerate(grams):
        if seen[g] > 1:
            repeated += i + window - max(i, upto)
            upto = i + window
    return repeated


def repeated_words_long(words: list[bytes], window: int) -> int:
    """The same count in a few arrays of the text's length: windows are numbered exactly, a word at a time."""
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), np.int64, len(words))
    m = len(words) - window + 1
    code = ids[:m]
    for k in range(1, window):
        code = np.unique(code * len(number) + ids[k : k + m], return_inverse=True)[1]
    hit = np.bincount(code)[code] > 1
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, np.flatnonzero(hit), 1)
    np.add.at(edge, np.flatnonzero(hit) + window, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def measure(text: str | None, window: int = 5) -> tuple[int, ...]:
    """The counts of one text, in the order of COUNTS."""
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()
    n = len(words)
    chars = len(text) - sum(map(text.count, BLANKS))
    lines = [line for line in text.split("\n") if line.strip(BLANKS)]
    repeated = 0 if n < window else (repeated_words if n < LONG else repeated_words_long)(words, window)
    caps = sum(1 for w in words if len(w) > 1 and w.isupper())
    stops = sum(1 for w in words if w[-1:] in b".!?")
    tails = sum(1 for w in words if w[-1:] in b"#*$%&|<>")
    return (n, chars, sum(map(text.count, SYMBOLS)), len(lines) - len(set(lines)), repeated, len(lines), caps, stops, tails, sum(map(eq, words, words[1:])))


def counts(docs: DataFrame) -> DataFrame:
    """doc_id and the counts of all documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            made = np.array([measure(t) for t in b.column(1).to_pylist()], np.int64).reshape(-1, len(COUNTS))
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(made[:, i]) for i in range(len(COUNTS)))], ["doc_id", *COUNTS])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS))


def share(a: str, b: str) -> Column:
    return F.col(a) / F.greatest(F.col(b), F.lit(1))


def votes() -> dict[str, Column]:
    """The rules. Each looks at one side of a text: it votes bad (-1) beyond one bound, good (1) within another, and
    abstains (0) between them or where the text is too short to say."""
    rule = lambda bad, good: F.when(bad, -1).when(good, 1).otherwise(0)
    symbols, tails, capitals, stops, repeats, stutters = (share(c, "n_words") for c in ("n_symbols", "n_tails", "n_caps", "n_stops", "n_repeat_words", "n_stutters"))
    dup, mean = share("n_dup_lines", "n_lines"), share("word_chars", "n_words")
    return {
        "symbols": rule(symbols > 0.1, symbols < 0.02),
        "symbol_tails": rule(tails > 0.05, tails < 0.01),
        "capitals": rule(capitals > 0.05, capitals < 0.02),
        "stops": rule((stops > 0.25) | (stops < 0.03), stops.between(0.05, 0.15)),
        "dup_lines": rule(dup > 0.1, F.col("n_dup_lines") == 0),
        "repeats": rule(repeats > 0.1, repeats < 0.02),
        "stutters": rule(stutters > 0.05, stutters < 0.02),
        "word_length": rule((mean < 4.2) | (mean > 6.2), mean.between(4.5, 5.7)),
        "length": rule(F.col("n_words") < 30, F.col("n_words") >= 100),
    }


VOTES = (-1, 0, 1)
#: What is believed of any rule before votes are seen: how often it votes bad, abstains, votes good, on bad and on good texts.
BELIEF = np.array([[0.25, 0.25, 0.5], [0.05, 0.15, 0.8]])


def evidence(table: np.ndarray) -> np.ndarray:
    """How much each vote of each rule speaks for good (rules x votes), from the rules' tables by class.

    A bad vote never speaks for good nor a good vote for bad, whatever was estimated; this fixes which class is called good.
    """
    lean = np.log(table[1]) - np.log(table[0])
    lean[:, 0], lean[:, 2] = np.minimum(lean[:, 0], 0), np.maximum(lean[:, 2], 0)
    return lean


def estimate(patterns: np.ndarray, n: np.ndarray, strength: float = 10.0, rounds: int = 500) -> tuple[np.ndarray, np.ndarray, float]:
    """The posterior of good by vote pattern, each rule's table of votes by class (class x rule x vote), and the share
    of good texts, by expectation-maximisation from n texts of each pattern.

    Rules vote independently within a class. A rule's table says how reliable it is: one whose bad votes often fall on
    texts that the others call good counts little, and so does one that votes alike on both. `strength` texts of the
    general belief are added to each class.
    """
    one = np.stack([patterns == v for v in VOTES], 2).astype(float)
    post = 1 / (1 + np.exp(-(0.5 * (patterns > 0).sum(1) - 2.0 * (patterns < 0).sum(1))))
    for _ in range(rounds):
        weight = np.stack([n * (1 - post), n * post])
        good = float((weight[1].sum() + 1) / (n.sum() + 2))
        table = np.einsum("cp,prv->crv", weight, one) + strength * BELIEF[:, None, :]
        table /= table.sum(2, keepdims=True)
        lean = np.log(good / (1 - good)) + np.einsum("prv,rv->p", one, evidence(table))
        new = 1 / (1 + np.exp(-np.clip(lean, -500, 500)))
        done, post = np.abs(new - post).max() < 1e-12, new
        if done:
            break
    return post, table, good


def judge(docs: DataFrame, threshold: float = 0.5) -> DataFrame:
    """doc_id, the counts, base_failed, kept and p_good of all documents."""
    rules = votes()
    measured = cut(counts(docs))
    voted = measured.withColumn("__votes", F.array(*(c.cast("int") for c in rules.values())))
    seen = voted.groupBy("__votes").agg(F.count(F.lit(1)).alias("n")).orderBy("__votes").collect()  # at most 3 ** rules rows
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    p_good = F.lit(0.0)
    if seen:
        post, _, _ = estimate(np.array([r[0] for r in seen]), np.array([r[1] for r in seen], float))
        known = docs.sparkSession.createDataFrame([(r[0], round(float(p), 9)) for r, p in zip(seen, post, strict=True)], "__votes array<int>, p_good double")
        voted = voted.join(F.broadcast(known), "__votes")
        p_good = F.col("p_good")
    out = voted.select("doc_id", *COUNTS[:5], failed.alias("base_failed"), (~failed & (p_good >= threshold)).alias("kept"), p_good.alias("p_good"))
    return out
