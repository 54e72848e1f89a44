"""The given tables, their catalog, and the store back ends of the knowledge base."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

STAR = ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"]
# The columns whose values become enum records.
ENUM_COLUMNS = [
    ("region", "r_name"), ("nation", "n_name"), ("customer", "c_mktsegment"), ("part", "p_brand"), ("part", "p_type"),
    ("orders", "o_orderstatus"), ("orders", "o_orderpriority"), ("lineitem", "l_returnflag"), ("events", "event_type"),
]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table. Times without zone become UTC timestamps, as watermarks want them."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.withColumns({c: F.col(c).cast("timestamp") for c, kind in df.dtypes if kind == "timestamp_ntz"})


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def catalog(spark: SparkSession, sf_dir: str, names: list[str] = STAR) -> DataFrame:
    """One row for each column, read from the schemas alone."""
    rows = [(t, f.name, i, f.dataType.simpleString(), f.nullable) for t in names for i, f in enumerate(table(spark, sf_dir, t).schema.fields)]
    return spark.createDataFrame(rows, "tab string, col string, ordinal int, kind string, nullable boolean")


def enum_values(spark: SparkSession, sf_dir: str, columns: list[tuple[str, str]] = ENUM_COLUMNS) -> DataFrame:
    """tab, col, val: the distinct values of categorical columns; each is one pruned scan with partial aggregation."""
    return union([table(spark, sf_dir, t).select(F.lit(t).alias("tab"), F.lit(c).alias("col"), F.col(c).alias("val")).distinct() for t, c in columns])


ENUM_SQL = " UNION ALL ".join(f"SELECT DISTINCT '{t}' AS tab, '{c}' AS col, {c} AS val FROM {t}" for t, c in ENUM_COLUMNS)


def save(df: DataFrame, where: str, backend: str = "parquet", partition_by: list[str] | None = None) -> None:
    """Keep records as a view (memory), as JSON files, as Parquet, ORC or CSV files, or as a catalog table."""
    if backend == "memory":
        df.createOrReplaceTempView(where)
        return
    writer = df.write.mode("overwrite")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if backend == "table":
        writer.saveAsTable(where)
    elif backend == "csv":
        writer.option("header", True).csv(where)
    else:
        writer.format(backend).save(where)


def load(spark: SparkSession, where: str, backend: str = "parquet", schema=None) -> DataFrame:
    if backend in ("memory", "table"):
        return spark.table(where)
    reader = spark.read if schema is None else spark.read.schema(schema)
    return reader.option("header", True).csv(where) if backend == "csv" else reader.format(backend).load(where)
