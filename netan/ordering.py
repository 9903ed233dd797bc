"""Sums and places in one order over a whole table, without a task that sees it whole."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from netan.storage import written


def running(rows: DataFrame, by: list[Column], amount: Column, out: str) -> DataFrame:
    """rows with `out`: the sum of amount over all rows before, in the order of `by`, which should tell rows apart.

    Ranges of the order are summed and put in order apart; a row for each range is all that one task sees together.
    """
    columns = rows.columns
    rows = written(rows.withColumn("_amount", amount).repartitionByRange(*by).withColumn("_range", F.spark_partition_id()), "ranges")
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    base = rows.groupBy("_range").agg(F.sum("_amount").alias("_sum")).select("_range", F.coalesce(F.sum("_sum").over(before), F.lit(0)).alias("_base"))
    inner = Window.partitionBy("_range").orderBy(*by).rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("_inner", F.coalesce(F.sum("_amount").over(inner), F.lit(0))).join(F.broadcast(base), "_range")
    return rows.select(*columns, (F.col("_base") + F.col("_inner")).alias(out))


def numbered(rows: DataFrame, column: str, out: str) -> DataFrame:
    """(column, out): its different values, numbered from 1 on in their order."""
    values = rows.select(column).distinct()
    return running(values, [F.col(column).asc()], F.lit(1), out).select(column, (F.col(out) + 1).cast("long").alias(out))


def ranked(rows: DataFrame, column: str, out: str) -> DataFrame:
    """rows with `out`: 1 and the number of rows whose column is higher."""
    counts = rows.groupBy(column).agg(F.count("*").alias("_n"))
    places = running(counts, [F.col(column).desc()], F.col("_n"), out).select(column, (F.col(out) + 1).cast("long").alias(out))
    return rows.join(places, column)
