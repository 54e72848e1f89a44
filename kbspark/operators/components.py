"""Connected components of an edge table by alternating large-star and small-star rounds."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kbspark.session import cut


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def _on_driver(edges: DataFrame) -> DataFrame:
    """The same for edges that fit the driver: roots hook on to the least root beside them until no edge joins two."""
    found = edges.toArrow()
    nodes, ends = np.unique(np.concatenate([found["u"].to_numpy(), found["v"].to_numpy()]), return_inverse=True)
    u, v = ends[: len(ends) // 2], ends[len(ends) // 2 :]
    root = np.arange(len(nodes))
    while (root[u] != root[v]).any():
        a, b = root[u], root[v]
        np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
        while (root != (up := root[root])).any():
            root = up
    return edges.sparkSession.createDataFrame(pa.table({"node": nodes, "root": nodes[root]}))


def components(edges: DataFrame, max_rounds: int = 60, few: int = 0) -> DataFrame:
    """node and root (the least node reachable) of all nodes on an edge; edges has columns u and v (long).

    Every round joins the edges with one row per node, so a node of many edges is split by the skew join,
    and is written to the shared folder. Ends when a round changes no edge. At most `few` distinct edges go to the
    driver, as the rounds' tasks would take longer than the edges.
    """
    now = cut(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    mark = _mark(now)
    if 0 < mark[0] <= few:
        return _on_driver(now)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = small.union(down.select("u", F.col("m").alias("v"))).distinct()
        now = cut(small)
        then, mark = mark, _mark(now)
        if then == mark:
            break
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    roots = now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return roots.union(now.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct()
