"""Measures: execution accuracy, soft row F1, row-pair weights, retrieval, difficulty, error causes, cost."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kbspark.operators.extract import CALLS

# Results to compare are rows of (case, row_no, cells): an array of canonical cells per row.


def bag_equal(pred: DataFrame, gold: DataFrame, keys: list[Column]) -> DataFrame:
    """case and equal (0/1): the two sides agree on the count of every key. A full join of counts, nothing collected."""
    n = lambda df, name: df.groupBy("case", *keys).agg(F.count(F.lit(1)).alias(name))
    names = [c for c in n(gold, "g").columns if c not in ("g",)]
    both = n(pred, "p").join(n(gold, "g"), names, "full")
    return both.groupBy("case").agg(F.min((F.coalesce("p", F.lit(0)) == F.coalesce("g", F.lit(0))).cast("int")).alias("score"))


def execution(pred: DataFrame, gold: DataFrame, mode: str = "bag") -> DataFrame:
    """case and score 1 or 0. set: distinct rows; bag: rows with multiplicity; ordered: also the place."""
    sig = F.array_join(F.array_sort("cells"), "\x1f").alias("sig")
    if mode == "set":
        pred, gold = pred.select("case", sig).distinct(), gold.select("case", sig).distinct()
        return bag_equal(pred, gold, [F.col("sig")])
    keys = [sig, F.col("row_no")] if mode == "ordered" else [sig]
    return bag_equal(pred, gold, keys)


def soft_f1(pred: DataFrame, gold: DataFrame) -> DataFrame:
    """case and score: mean row F1 of rows at the same place, cells as sets; a missing partner counts 0."""
    p = pred.select("case", "row_no", F.array_distinct("cells").alias("p"))
    g = gold.select("case", "row_no", F.array_distinct("cells").alias("g"))
    both = p.join(g, ["case", "row_no"], "full")
    hit = F.size(F.array_intersect("p", "g"))
    f1 = F.when(F.col("p").isNull() | F.col("g").isNull(), 0.0).otherwise(2 * hit / (F.size("p") + F.size("g")))
    return both.groupBy("case").agg(F.round(F.avg(f1), 6).alias("score"))


def f_beta(pre: Column, rec: Column, beta: float) -> Column:
    return F.when(pre + rec == 0, 0.0).otherwise((1 + beta**2) * pre * rec / (beta**2 * pre + rec))


def weights(pred: DataFrame, gold: DataFrame, beta: float = 2.0) -> DataFrame:
    """case, i, j, weight of the row pairs that share a cell. Pairs come from a join on cells, not from all rows."""
    side = lambda df, n: df.select("case", F.col("row_no").alias(n), F.size(F.array_distinct("cells")).alias(f"n{n}"), F.explode(F.array_distinct("cells")).alias("cell"))
    shared = side(pred, "i").join(side(gold, "j"), ["case", "cell"]).groupBy("case", "i", "j").agg(F.count(F.lit(1)).alias("c"), F.max("ni").alias("ni"), F.max("nj").alias("nj"))
    return shared.select("case", "i", "j", F.round(f_beta(F.col("c") / F.col("ni"), F.col("c") / F.col("nj"), beta), 6).alias("weight"))


def retrieval(hits: DataFrame, gold: DataFrame, ks: list[int]) -> DataFrame:
    """k, recall, precision, mrr over the questions of gold. hits: q, rank, id; gold: q, id."""
    n = gold.groupBy("q").agg(F.count_distinct("id").alias("n"))
    right = hits.join(gold.distinct(), ["q", "id"])
    per = right.groupBy("q").agg(F.min("rank").alias("first"), *(F.count_if(F.col("rank") <= k).alias(f"r{k}") for k in ks))
    all_ = n.join(per, "q", "left")
    got = all_.agg(F.round(F.avg(F.coalesce(1 / F.col("first"), F.lit(0.0))), 6).alias("mrr"), *(F.round(F.avg(F.coalesce(F.col(f"r{k}") / F.col("n"), F.lit(0.0))), 6).alias(f"rec{k}") for k in ks), *(F.round(F.avg(F.coalesce(F.col(f"r{k}"), F.lit(0)) / k), 6).alias(f"pre{k}") for k in ks))
    return got.select(F.inline(F.array(*(F.struct(F.lit(k).alias("k"), F.col(f"rec{k}").alias("recall"), F.col(f"pre{k}").alias("precision"), F.col("mrr").alias("mrr")) for k in ks))))


def neighbour_recall(approx: DataFrame, exact: DataFrame) -> DataFrame:
    """One row: the share of exact neighbours that the approximate answer has."""
    hit = exact.join(approx.select("q", "id", F.lit(1).alias("hit")), ["q", "id"], "left")
    return hit.agg(F.round(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("recall"))


def by_difficulty(evals: DataFrame) -> DataFrame:
    """difficulty, share, ex, error_share and diff, with an overall row. evals: difficulty, correct (0/1)."""
    g = evals.rollup("difficulty").agg(F.count(F.lit(1)).alias("n"), F.sum("correct").alias("ok"))
    tot = evals.agg(F.count(F.lit(1)).alias("n_all"), F.sum(1 - F.col("correct")).alias("e_all"))
    j = g.join(F.broadcast(tot))
    share, err = F.col("n") / F.col("n_all"), (F.col("n") - F.col("ok")) / F.greatest(F.col("e_all"), F.lit(1))
    return j.select(F.coalesce("difficulty", F.lit("overall")).alias("difficulty"), "n", F.round(share, 6).alias("share"), F.round(F.col("ok") / F.col("n"), 6).alias("ex"), F.round(err, 6).alias("error_share"), F.round(err - share, 6).alias("diff"))


def valid_rate(results: DataFrame) -> DataFrame:
    return results.groupBy("tier").agg(F.round(F.count_if(F.col("status") == "ok") / F.count(F.lit(1)), 6).alias("valid"))


def meaningful(results: DataFrame) -> DataFrame:
    """Share of results that have a row with a value that isn't null. results: case, cells."""
    ok = F.max(F.exists("cells", lambda c: c != "<null>").cast("int"))
    return results.groupBy("case").agg(ok.alias("ok")).agg(F.round(F.avg("ok"), 6).alias("meaningful"))


def cost(runs: DataFrame) -> DataFrame:
    """tier, samples, median and mean latency. runs: tier, latency_ms."""
    return runs.groupBy("tier").agg(F.count(F.lit(1)).alias("samples"), F.percentile("latency_ms", 0.5).alias("p50"), F.round(F.avg("latency_ms"), 3).alias("mean"))


CAUSES = ["invalid", "predicate", "enum", "column", "format", "ratio", "null", "concat", "computation", "columns", "ties", "distinct", "reasoning"]


def classify(gold: list[tuple], pred: list[tuple]) -> str:
    """The cause of an error from the facts (and calls) of two queries, as a decision list over their differences."""
    g, p = set(gold), set(pred)
    only_g, only_p = g - p, p - g
    if any(f[0] == "error" for f in p):
        return "invalid"
    preds = lambda fs: {f[2:5] for f in fs if f[0] == "predicate"}
    a, b = preds(only_g), preds(only_p)
    if a or b:
        if len(a) == len(b) == 1:
            (gc, go, gv), (pc, po, pv) = next(iter(a)), next(iter(b))
            if gc == pc and go == po:
                return "format" if "".join(filter(str.isdigit, gv)) == "".join(filter(str.isdigit, pv)) != "" else "enum"
            if gv == pv:
                return "column"
        return "predicate"
    if any(f[0] == "scale" for f in only_g | only_p):
        return "ratio"
    changed = {f[2] for f in only_g | only_p if f[0] == "call"}
    for cause, names in CALLS.items():
        if changed.intersection(names):
            return cause
    clauses = {f[4] for f in only_g | only_p if f[0] == "clause"}
    if "distinct" in clauses:
        return "distinct"
    if "sort" in clauses or "globallimit" in clauses:
        return "ties"
    if any(f[0] == "column" for f in only_g | only_p):
        return "columns"
    return "reasoning" if only_g or only_p else "same"
