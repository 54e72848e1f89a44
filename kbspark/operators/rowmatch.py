"""The order-aware row-matching F-beta: the best pairing of predicted and true rows.

Unordered: a maximum-weight assignment, solved for each connected component of the graph of pairs that share a
cell; ordered: the best pairing that doesn't cross, by dynamic programming after equal ends are taken off. The
score is the pairing's weight over the larger number of rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kbspark.operators.components import components as connected
from kbspark.operators.measure import weights
from kbspark.session import cut


def assignment(w: np.ndarray) -> float:
    """The weight of the best assignment of rows to columns (shortest augmenting paths with potentials)."""
    if w.shape[0] > w.shape[1]:
        w = w.T
    n, m = w.shape
    cost = w.max(initial=0.0) - w
    u, v = np.zeros(n + 1), np.zeros(m + 1)
    row_of = np.zeros(m + 1, int)
    for i in range(1, n + 1):
        row_of[0], j0 = i, 0
        least, back, used = np.full(m + 1, np.inf), np.zeros(m + 1, int), np.zeros(m + 1, bool)
        while True:
            used[j0] = True
            i0 = row_of[j0]
            cur = cost[i0 - 1] - u[i0] - v[1:]
            better = ~used[1:] & (cur < least[1:])
            least[1:][better] = cur[better]
            back[1:][better] = j0
            open_ = np.where(used[1:], np.inf, least[1:])
            j1 = int(open_.argmin()) + 1
            d = least[j1]
            u[row_of[used]] += d
            v[used] -= d
            least[~used] -= d
            j0 = j1
            if row_of[j0] == 0:
                break
        while j0:
            row_of[j0] = row_of[back[j0]]
            j0 = back[j0]
    return float(sum(w[row_of[j] - 1, j - 1] for j in range(1, m + 1) if row_of[j]))


def components(i: np.ndarray, j: np.ndarray) -> list[np.ndarray]:
    """Edge numbers by connected component of a bipartite edge list."""
    root: dict[tuple[str, int], tuple[str, int]] = {}

    def find(x):
        while root.setdefault(x, x) != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for a, b in zip(i.tolist(), j.tolist(), strict=True):
        root[find(("i", a))] = find(("j", b))
    by: dict = {}
    for k, a in enumerate(i.tolist()):
        by.setdefault(find(("i", a)), []).append(k)
    return [np.array(v) for v in by.values()]


def best_unordered(i: np.ndarray, j: np.ndarray, w: np.ndarray) -> float:
    total = 0.0
    for edges in components(i, j):
        a, ai = np.unique(i[edges], return_inverse=True)
        b, bj = np.unique(j[edges], return_inverse=True)
        if len(a) == 1 or len(b) == 1:
            total += float(w[edges].max())
            continue
        m = np.zeros((len(a), len(b)))
        m[ai, bj] = w[edges]
        total += assignment(m)
    return total


def best_ordered(i: np.ndarray, j: np.ndarray, w: np.ndarray) -> float:
    """The heaviest set of pairs that all grow in both places: a sweep over i with a prefix-maximum tree over j.

    Work is pairs times the logarithm of the rows, as only pairs that share a cell have weight.
    """
    if not len(i):
        return 0.0
    js = np.unique(j)
    at = np.searchsorted(js, j) + 1
    tree = np.zeros(len(js) + 1)

    def upto(k: int) -> float:
        best = 0.0
        while k:
            best = max(best, tree[k])
            k -= k & -k
        return best

    order = np.lexsort((j, i))
    k = 0
    while k < len(order):
        same = k
        while same < len(order) and i[order[same]] == i[order[k]]:
            same += 1
        found = [(int(at[e]), upto(int(at[e]) - 1) + float(w[e])) for e in order[k:same]]
        for pos, value in found:
            while pos < len(tree):
                tree[pos] = max(tree[pos], value)
                pos += pos & -pos
        k = same
    return upto(len(js))


def by_component(pairs: DataFrame) -> DataFrame:
    """pairs with part: the connected component of each pair's case, found by distributed rounds."""
    node = lambda side, n: F.xxhash64("case", F.lit(side), n)
    ends = pairs.withColumn("u", node("p", F.col("i"))).withColumn("v", node("g", F.col("j")))
    return ends.join(connected(ends.select("u", "v")).select(F.col("node").alias("u"), F.col("root").alias("part")), "u").drop("u", "v")


def score(pred: DataFrame, gold: DataFrame, ordered: bool | None = False, beta: float = 2.0, large: int = 200_000) -> DataFrame:
    """case and score for all cases that either side has; a case that neither has is empty on both sides, 1 by definition.

    A case's pairs are solved in one task up to `large` of them; beyond that (unordered) each connected component
    of the case is a task of its own, as the assignment splits along components.
    """
    pairs = weights(pred, gold, beta)
    best = best_ordered if ordered else best_unordered
    kind = dict(pred.dtypes)["case"]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        total = best(pdf["i"].to_numpy(), pdf["j"].to_numpy(), pdf["weight"].to_numpy())
        return pd.DataFrame({"case": [pdf["case"].iloc[0]], "total": [total]})

    schema = f"case {kind}, total double"
    if ordered:
        totals = pairs.groupBy("case").applyInPandas(run, schema)
    else:
        pairs = cut(pairs)
        sizes = pairs.groupBy("case").agg(F.count(F.lit(1)).alias("n"))
        big = sizes.where(F.col("n") > large).select("case")
        totals = pairs.join(big, "case", "left_anti").groupBy("case").applyInPandas(run, schema)
        if not big.isEmpty():
            parts = by_component(pairs.join(big, "case", "left_semi")).groupBy("case", "part").applyInPandas(run, schema)
            totals = totals.union(parts.groupBy("case").agg(F.sum("total").alias("total")))
    n = lambda df, name: df.groupBy("case").agg(F.count(F.lit(1)).alias(name))
    rows = n(pred, "np").join(n(gold, "ng"), "case", "full")
    return rows.join(totals, "case", "left").select("case", F.round(F.coalesce("total", F.lit(0.0)) / F.greatest(F.coalesce("np", F.lit(0)), F.coalesce("ng", F.lit(0))), 6).alias("score"))


def per_question(pred: DataFrame, gold: DataFrame, cases: DataFrame, beta: float = 2.0) -> DataFrame:
    """case and score of all questions. cases: case, is_ordered (whether the gold query orders its rows) and failed
    (whether the predicted query didn't run). A failed one scores 0, a result empty on both sides 1."""
    parts = []
    for ordered in (False, True):
        mine = cases.where(F.coalesce("is_ordered", F.lit(False)) == ordered).select("case")
        parts.append(score(pred.join(mine, "case", "left_semi"), gold.join(mine, "case", "left_semi"), ordered, beta))
    scored = cases.join(parts[0].union(parts[1]), "case", "left")
    return scored.select("case", F.when(F.coalesce("failed", F.lit(False)), 0.0).otherwise(F.coalesce("score", F.lit(1.0))).alias("score"))


def final_score(pred: DataFrame, gold: DataFrame, cases: DataFrame, beta: float = 2.0) -> DataFrame:
    """One row: questions, and the mean row-matching score over them."""
    return per_question(pred, gold, cases, beta).agg(F.count(F.lit(1)).alias("questions"), F.round(F.avg("score"), 6).alias("score"))
