"""What an agent asks of a database: its columns, tables and whole, and columns by a word's letters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kbspark.operators import lexical
from kbspark.operators.profile import NUMBER


def kind_of(type_name: str) -> str:
    if type_name in NUMBER or type_name.startswith("decimal"):
        return "numeric"
    return "temporal" if type_name.startswith(("timestamp", "date")) else "text"


def column_info(df: DataFrame, name: str, columns: list[str] | None = None) -> DataFrame:
    """tab, col, kind, n_rows, n_null, info: a row for each column, all counted in one scan of the columns named."""
    kinds = {c: kind_of(k) for c, k in df.dtypes if columns is None or c in columns}
    wide = df.agg(F.count(F.lit(1)).alias("__n"), *(F.count(c).alias(c) for c in kinds))
    rows = wide.select(F.inline(F.array(*(F.struct(F.lit(name).alias("tab"), F.lit(c).alias("col"), F.lit(k).alias("kind"), F.col("__n").alias("n_rows"), (F.col("__n") - F.col(c)).alias("n_null")) for c, k in kinds.items()))))
    return rows.withColumn("info", F.concat("tab", F.lit("."), "col", F.lit(": "), "kind", F.lit(", "), F.col("n_null").cast("string"), F.lit(" nulls")))


def scanned(infos: DataFrame) -> DataFrame:
    """tab and col of rows of column_info, the columns as scans found them: each one's values were counted."""
    return infos.where("n_null BETWEEN 0 AND n_rows").select("tab", "col")


def table_info(columns: DataFrame) -> DataFrame:
    """tab, n_rows, n_columns, info: from rows of column_info, columns by name."""
    listed = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("col", "kind"))), lambda c: F.concat(c["col"], F.lit(" ("), c["kind"], F.lit(")"))), ", ")
    out = columns.groupBy("tab").agg(F.max("n_rows").alias("n_rows"), F.count(F.lit(1)).alias("n_columns"), listed.alias("listed"))
    return out.select("tab", "n_rows", "n_columns", F.concat("tab", F.lit(": "), F.col("n_rows").cast("string"), F.lit(" rows; "), "listed").alias("info"))


def db_info(tables: DataFrame) -> DataFrame:
    """One row n_tables, n_rows, info: from rows of table_info, which a schema bounds."""
    names = F.array_join(F.array_sort(F.collect_list("tab")), ", ")
    out = tables.agg(F.count(F.lit(1)).alias("n_tables"), F.sum("n_rows").alias("n_rows"), names.alias("names"))
    return out.select("n_tables", "n_rows", F.concat(F.col("n_tables").cast("string"), F.lit(" tables: "), "names").alias("info"))


def fuzzy_column(keywords: DataFrame, columns: DataFrame, k: int = 5) -> DataFrame:
    """keyword, value (`table.column`), score, rank: columns by the share of the keyword's 3-grams in their full names."""
    return lexical.top(lexical.containment(keywords, columns.select(F.concat("tab", F.lit("."), "col").alias("value"))), k)
