"""Vectors: exact neighbours in blocks, hyperplane buckets with probes, inverted cells, MMR."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kbspark.session import cut

MAX_QUERIES = 100_000


def score(a: np.ndarray, b: np.ndarray, metric: str) -> np.ndarray:
    """Larger is nearer: cosine, dot product or negated distance of all pairs."""
    if metric == "l2":
        return -np.sqrt(np.maximum((a**2).sum(1)[:, None] + (b**2).sum(1)[None] - 2 * a @ b.T, 0))
    if metric == "cosine":
        a = a / np.maximum(np.linalg.norm(a, axis=1, keepdims=True), 1e-12)
        b = b / np.maximum(np.linalg.norm(b, axis=1, keepdims=True), 1e-12)
    return a @ b.T


def ranked(df: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("q").orderBy(F.desc("score"), "id")
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def nearest(s: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of each row's k largest finite scores; ties are cut by column."""
    k, s = min(k, s.shape[1]), np.where(np.isnan(s), -np.inf, s)
    edge = np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k, None]
    above, tied = s > edge, s == edge
    at, col = np.nonzero(above | (tied & (tied.cumsum(1) <= k - above.sum(1)[:, None])))
    keep = np.isfinite(s[at, col])
    return at[keep], col[keep]


def best_in_batches(qid: np.ndarray, qv: np.ndarray, k: int, metric: str, leave_self: bool, place=None, visits: np.ndarray | None = None):
    """What a worker does with batches of id and vec: the k best of each batch for every query, or, with place (a cell
    of each vector) and visits (queries by cells, whether one visits the other), of each cell for the queries that visit it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows or not len(qid):
                continue
            ids = b.column(0).to_numpy()
            v = np.array(b.column(1).to_pylist(), np.float64)
            by = np.argsort(ids, kind="stable")  # ties are cut by column, so by id
            ids, v = ids[by], v[by]
            of = np.zeros(len(ids), np.int64) if place is None else place(v)
            for cell in np.unique(of):
                mine = np.flatnonzero(of == cell)
                asked = np.arange(len(qid)) if visits is None else np.flatnonzero(visits[:, cell])
                for low in range(0, len(asked), 512):
                    some = asked[low : low + 512]
                    s = np.round(score(qv[some], v[mine], metric), 6)
                    if leave_self:
                        s[qid[some][:, None] == ids[mine][None]] = -np.inf
                    at, col = nearest(s, k)
                    yield pa.RecordBatch.from_arrays([pa.array(qid[some][at]), pa.array(ids[mine][col]), pa.array(s[at, col])], ["q", "id", "score"])

    return run


def collected(queries: DataFrame, most: int = MAX_QUERIES) -> tuple[np.ndarray, np.ndarray]:
    rows = queries.select("q", "vec").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError("give the queries in blocks, or use knn_blocks")
    return np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.float64)


def scored(base: DataFrame, run, k: int) -> DataFrame:
    return ranked(base.select(F.col("id").cast("long"), "vec").mapInArrow(run, "q long, id long, score double"), k)


def knn(queries: DataFrame, base: DataFrame, k: int, metric: str = "cosine", leave_self: bool = True) -> DataFrame:
    """q, id, score, rank. The stated query set (checked size) goes to every block of the base; each block sends on
    its own k best only, so what is shuffled is blocks times k rows a query. queries: q, vec; base: id, vec."""
    return scored(base, best_in_batches(*collected(queries), k, metric, leave_self), k)


def knn_blocks(queries: DataFrame, base: DataFrame, k: int, metric: str = "cosine", leave_self: bool = True, block: int = MAX_QUERIES // 2) -> DataFrame:
    """knn for any number of queries, exact at every size: blocks of about `block` queries, by a hash of q, one after
    the other against all of the base; each block's answer is written before the next begins."""
    return by_blocks(queries, block, lambda some: knn(some, base, k, metric, leave_self))


def by_blocks(queries: DataFrame, block: int, answer) -> DataFrame:
    """The answers to blocks of about `block` queries, one written after the other; to all at once if they are no more."""
    parts = -(-queries.count() // block) or 1
    if parts == 1:
        return answer(queries)
    part = lambda i: queries.where(F.pmod(F.xxhash64("q"), F.lit(parts)) == i)
    return reduce(DataFrame.union, (cut(answer(part(i))) for i in range(parts)))


def hyperplanes(dim: int, bits: int, seed: int = 5) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((bits, dim))


def ann(queries: DataFrame, base: DataFrame, k: int, bits: int = 4, probes: int | None = None, dim: int = 64, block: int = MAX_QUERIES // 2) -> DataFrame:
    """Approximate neighbours: a query visits its bucket (the signs of its vector against the hyperplanes, as a number)
    and those within some flipped bits; exact scores follow, in blocks of vectors of one bucket.

    probes is the number of bits that may differ (default 2); with all bits the answer is exact.
    """
    flips = 2 if probes is None else probes
    planes = hyperplanes(dim, bits)
    near = np.array([[(m ^ c).bit_count() <= flips for c in range(1 << bits)] for m in range(1 << bits)])
    place = lambda v: ((v @ planes.T >= 0) << np.arange(bits)).sum(1)

    def answer(some: DataFrame) -> DataFrame:
        qid, qv = collected(some)
        visits = near[place(qv)] if len(qid) else None
        return scored(base, best_in_batches(qid, qv, k, "cosine", True, place, visits), k)

    return by_blocks(queries, block, answer)


def cells(base: DataFrame, n_cells: int, sample: int = 10_000, seed: int = 1, rounds: int = 8) -> np.ndarray:
    """Cell centres by k-means over a bounded sample (its size is the parameter)."""
    rows = base.orderBy(F.xxhash64("id")).limit(sample).collect()
    v = np.array([r["vec"] for r in rows], np.float64)
    v /= np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)
    c = v[np.random.default_rng(seed).choice(len(v), min(n_cells, len(v)), replace=False)]
    for _ in range(rounds):
        of = (v @ c.T).argmax(1)
        c = np.stack([v[of == i].mean(0) if (of == i).any() else c[i] for i in range(len(c))])
    return c


def ivf(queries: DataFrame, base: DataFrame, k: int, centres: np.ndarray, probes: int = 4, block: int = MAX_QUERIES // 2) -> DataFrame:
    """Approximate neighbours by inverted cells: every base row is in one cell; queries visit the nearest few."""
    place = lambda v: score(v, centres, "cosine").argmax(1)

    def answer(some: DataFrame) -> DataFrame:
        qid, qv = collected(some)
        visits = np.zeros((len(qid), len(centres)), bool)
        if len(qid):
            np.put_along_axis(visits, np.argsort(-score(qv, centres, "cosine"), axis=1)[:, :probes], True, axis=1)
        return scored(base, best_in_batches(qid, qv, k, "cosine", True, place, visits), k)

    return by_blocks(queries, block, answer)


def mmr(candidates: DataFrame, k: int, lam: float = 0.7) -> DataFrame:
    """q, id, rank: maximal marginal relevance over each query's candidates (q, id, score, vec; few a query)."""

    def pick(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["score", "id"], ascending=[False, True]).reset_index(drop=True)
        v = np.array(pdf["vec"].tolist(), np.float64)
        sim, chosen = score(v, v, "cosine"), []
        while len(chosen) < min(k, len(pdf)):
            far = sim[:, chosen].max(1) if chosen else np.zeros(len(pdf))
            worth = lam * pdf["score"].to_numpy() - (1 - lam) * far
            worth[chosen] = -np.inf
            chosen.append(int(np.round(worth, 9).argmax()))
        return pd.DataFrame({"q": pdf["q"].iloc[chosen].to_numpy(), "id": pdf["id"].iloc[chosen].to_numpy(), "rank": np.arange(1, len(chosen) + 1)})

    return candidates.groupBy("q").applyInPandas(pick, "q long, id long, rank int")
