"""Periods and metrics of the finance workload."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def period(ts: Column) -> Column:
    return F.date_format(ts, "yyyyMM")


def current_period(as_of: Column, update_day: int = 10) -> Column:
    """Before the update day a month's figures aren't in, so `this month` is the one before."""
    return period(F.when(F.dayofmonth(as_of) < update_day, F.add_months(as_of, -1)).otherwise(as_of.cast("date")))


def fiscal_year(ts: Column, first_month: int = 4) -> Column:
    """Named by the calendar year in which it ends; from January it is the calendar year."""
    return F.year(ts) + (F.month(ts) >= first_month).cast("int") * (1 if first_month > 1 else 0)


def growth(end: Column, start: Column) -> Column:
    """Change over the absolute base; 0 on a zero base, nulls count as 0."""
    e, s = F.coalesce(end, F.lit(0.0)), F.coalesce(start, F.lit(0.0))
    return F.when(s == 0, F.lit(0.0)).otherwise((e - s) / F.abs(s))


def ratio(a: Column, b: Column) -> Column:
    return F.when(F.coalesce(b, F.lit(0.0)) == 0, F.lit(0.0)).otherwise(F.coalesce(a, F.lit(0.0)) / b)


def money(x: Column | str) -> Column:
    """Two places. A millionth first, so that halves of a cent, inexact in binary, round up in any order of summing."""
    return F.round((F.col(x) if isinstance(x, str) else x) + 1e-6, 2)


def ytd_range(ytd_end: Column, ytd_before: Column, first_month: Column) -> Column:
    """A range as a difference of year-to-date figures; one that begins in January subtracts nothing."""
    return ytd_end - F.when(first_month == 1, F.lit(0.0)).otherwise(F.coalesce(ytd_before, F.lit(0.0)))


def register(spark) -> None:
    """The functions as temporary SQL functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION growth(e DOUBLE, s DOUBLE) RETURNS DOUBLE RETURN CASE WHEN coalesce(s, 0) = 0 THEN 0 ELSE (coalesce(e, 0) - s) / abs(s) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION current_period(t TIMESTAMP, d INT) RETURNS STRING RETURN date_format(CASE WHEN day(t) < d THEN add_months(t, -1) ELSE CAST(t AS DATE) END, 'yyyyMM')")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x) / sqrt(aggregate(a, 0D, (s, x) -> s + x * x) * aggregate(b, 0D, (s, x) -> s + x * x))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION containment(k STRING, v STRING) RETURNS DOUBLE RETURN size(array_intersect(transform(sequence(1, length(k) - 2), i -> substr(k, i, 3)), transform(sequence(1, greatest(length(v) - 2, 1)), i -> substr(v, i, 3)))) / size(array_distinct(transform(sequence(1, length(k) - 2), i -> substr(k, i, 3))))")
