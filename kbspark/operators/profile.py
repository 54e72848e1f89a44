"""Database profiling: types, formats, numeric, categorical and temporal profiles, keys, dependencies."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from kbspark.sources.tables import union

NUMBER = ("int", "bigint", "double", "float", "smallint", "tinyint")


def numeric_columns(df: DataFrame) -> list[str]:
    return [c for c, k in df.dtypes if k in NUMBER or k.startswith("decimal")]


def numeric(df: DataFrame, name: str, exact: bool = True) -> DataFrame:
    """tab, col, n_null, mean, min, p25, p50, p75, max, is_int. One scan; approx mode takes mergeable sketches."""
    cols = numeric_columns(df)
    quantile = (lambda c: F.percentile(c, [0.25, 0.5, 0.75])) if exact else (lambda c: F.percentile_approx(c, [0.25, 0.5, 0.75], 10000))
    aggs = []
    for c in cols:
        v = F.col(c).cast("double")
        aggs.append(F.struct(F.count_if(v.isNull()).alias("n_null"), F.avg(v).alias("mean"), F.min(v).alias("min"), quantile(v).alias("q"), F.max(v).alias("max"), F.bool_and(v == F.floor(v)).alias("is_int")).alias(c))
    wide = df.agg(*aggs)
    rows = wide.select(F.inline(F.array(*(F.struct(F.lit(name).alias("tab"), F.lit(c).alias("col"), F.col(c).alias("p")) for c in cols))))
    return rows.select("tab", "col", "p.n_null", F.round("p.mean", 4).alias("mean"), "p.min", F.col("p.q")[0].alias("p25"), F.col("p.q")[1].alias("p50"), F.col("p.q")[2].alias("p75"), "p.max", "p.is_int")


def categorical(df: DataFrame, name: str, columns: list[str], top: int = 5) -> DataFrame:
    """tab, col, value, n, share, cum_share, rank: the most frequent values. Aggregated before anything is ranked."""
    long = df.select(*(F.col(c).cast("string").alias(c) for c in columns)).unpivot([], columns, "col", "value")
    n = long.groupBy("col", "value").agg(F.count(F.lit(1)).alias("n"))
    order = Window.partitionBy("col").orderBy(F.desc("n"), "value")
    total = F.sum("n").over(Window.partitionBy("col"))
    run = F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, 0))
    out = n.select(F.lit(name).alias("tab"), "col", "value", "n", F.round(F.col("n") / total, 6).alias("share"), F.round(run / total, 6).alias("cum_share"), F.row_number().over(order).alias("rank"))
    return out.where(F.col("rank") <= top)


def temporal(df: DataFrame, name: str, columns: list[str]) -> DataFrame:
    wide = df.agg(*(F.struct(F.min(c).alias("a"), F.max(c).alias("b")).alias(c) for c in columns))
    show = lambda x: F.date_format(x, "yyyy-MM-dd HH:mm:ss")
    return wide.select(F.inline(F.array(*(F.struct(F.lit(name).alias("tab"), F.lit(c).alias("col"), show(F.col(c)["a"]).alias("first"), show(F.col(c)["b"]).alias("last")) for c in columns))))


def annotate(df: DataFrame, name: str, few: int = 100) -> DataFrame:
    """tab, col, kind: numeric, categorical, text or temporal, from one aggregation (distinct counts by sketch-free
    exact sets only for short strings; at scale pass a sample or a profile)."""
    aggs = {}
    for c, k in df.dtypes:
        if k in ("timestamp", "timestamp_ntz", "date"):
            aggs[c] = F.first(F.lit("temporal"))
        elif k in NUMBER:
            aggs[c] = F.first(F.lit("numeric"))
        else:
            aggs[c] = F.when(F.approx_count_distinct(c, 0.02) <= few, "categorical").otherwise("text")
    wide = df.agg(*(a.alias(c) for c, a in aggs.items()))
    return wide.select(F.inline(F.array(*(F.struct(F.lit(name).alias("tab"), F.lit(c).alias("col"), F.coalesce(F.col(c), F.lit("text")).alias("kind")) for c in aggs))))


def time_formats(df: DataFrame, column: str, formats: list[str]) -> DataFrame:
    """format and share of the values that parse by it, all formats in one scan."""
    wide = df.agg(*(F.count_if(F.try_to_timestamp(column, F.lit(f)).isNotNull()).alias(f"f{i}") for i, f in enumerate(formats)), F.count(column).alias("n"))
    return wide.select(F.inline(F.array(*(F.struct(F.lit(f).alias("format"), F.round(F.col(f"f{i}") / F.col("n"), 6).alias("share")) for i, f in enumerate(formats)))))


def keys(df: DataFrame, name: str, columns: list[str]) -> DataFrame:
    wide = df.agg(F.count(F.lit(1)).alias("__n"), *((F.count_distinct(c) == F.count(F.lit(1))).alias(c) for c in columns))
    return wide.select(F.inline(F.array(*(F.struct(F.lit(name).alias("tab"), F.lit(c).alias("col"), F.col(c).alias("is_unique")) for c in columns))))


def inclusion(child: DataFrame, child_col: str, parent: DataFrame, parent_col: str) -> Column | DataFrame:
    """How many child values have no parent: distinct values only are joined."""
    missing = child.select(F.col(child_col).alias("v")).distinct().join(parent.select(F.col(parent_col).alias("v")).distinct(), "v", "left_anti")
    return missing.agg(F.count(F.lit(1)).alias("missing"))


def dependency(df: DataFrame, x: str, y: str) -> DataFrame:
    """Whether x determines y: groups of x whose least and greatest y differ violate it."""
    g = df.groupBy(x).agg(F.min(y).alias("a"), F.max(y).alias("b"))
    return g.agg(F.count_if(F.col("a") != F.col("b")).alias("violations")).select(F.lit(x).alias("x"), F.lit(y).alias("y"), (F.col("violations") == 0).alias("holds"), "violations")


def taxonomy(found: DataFrame) -> DataFrame:
    """Levels from dependencies that hold in one direction only: child, parent."""
    h = found.where("holds").select("x", "y")
    back = h.select(F.col("y").alias("x"), F.col("x").alias("y"))
    return h.join(back, ["x", "y"], "left_anti").select(F.col("x").alias("child"), F.col("y").alias("parent"))


def describe(profiles: DataFrame) -> DataFrame:
    """A rule-made description for columns that have none; given text is never replaced."""
    made = F.concat_ws("", F.lit("Column "), "col", F.lit(" of "), "tab", F.lit(", "), F.coalesce("kind", F.lit("unknown")), F.lit("."))
    text = F.col("description") if "description" in profiles.columns else F.lit(None).cast("string")
    return profiles.withColumn("description", F.when(F.length(F.coalesce(text, F.lit(""))) > 0, text).otherwise(made))


def sizes(frames: dict[str, DataFrame]) -> DataFrame:
    return union([df.agg(F.count(F.lit(1)).alias("n_rows")).select(F.lit(t).alias("tab"), "n_rows", F.lit(len(df.columns)).alias("n_columns")) for t, df in frames.items()])
