"""Update logs (row_id, col_id, delta [, ts, site]): every change of a matrix is an addition to one entry."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from .tables import typed

EVENT_TYPES = 5


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order x line matrix from lineitem: 7 columns, several updates an entry."""
    return typed(spark, sf_dir, "lineitem").select(
        F.col("l_orderkey").alias("row_id"),
        (F.col("l_linenumber") - 1).alias("col_id"),
        F.col("l_extendedprice").alias("delta"),
        F.col("l_shipdate").alias("ts"),
        (F.col("l_suppkey") % 4).cast("int").alias("site"),
        F.col("l_returnflag").alias("flag"),
    )


def user_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User-day x event-type matrix from events; the five types in alphabetical order."""
    e = typed(spark, sf_dir, "events")
    kind = F.array_position(F.array(*[F.lit(t) for t in event_types(spark, sf_dir)]), F.col("event_type")) - 1
    return e.select(user_day(F.col("user_id"), F.col("ts")).alias("row_id"), kind.cast("int").alias("col_id"), F.col("value").alias("delta"), F.col("ts"))


def user_day(user: Column, ts: Column) -> Column:
    """One id for each user and calendar day."""
    return user * 100_000 + F.unix_date(F.to_date(ts))


def event_types(spark: SparkSession, sf_dir: str) -> list[str]:
    """The distinct types: a handful by the schema of the table, refused if there are more than a hundred."""
    found = [r[0] for r in typed(spark, sf_dir, "events").select("event_type").distinct().orderBy("event_type").limit(101).collect()]
    if len(found) > 100:
        raise ValueError("event_type is no small category")
    return found


def validate(updates: DataFrame, d: int) -> DataFrame:
    """The log as typed triples; what no sketch takes raises where it is read."""
    from ..operators.sketch import validated

    return validated(updates, d)


def from_wide(df: DataFrame, row: str, columns: list[str]) -> DataFrame:
    """Numeric columns of a table as updates, one each."""
    numbered = df.select(F.col(row).alias("row_id"), *[F.col(c).cast("double").alias(str(i)) for i, c in enumerate(columns)])
    long = numbered.unpivot("row_id", [str(i) for i in range(len(columns))], "col", "delta")
    return long.select("row_id", F.col("col").cast("int").alias("col_id"), "delta")


def retract(updates: DataFrame) -> DataFrame:
    """Updates that undo a log."""
    return updates.withColumn("delta", -F.col("delta"))


def from_history(df: DataFrame, row: str, col: str, value: str, order: list[str]) -> DataFrame:
    """Overwrites to additive updates: each value minus the one before it at the same entry."""
    w = Window.partitionBy(row, col).orderBy(*order)
    return df.select(F.col(row).alias("row_id"), F.col(col).alias("col_id"), (F.col(value) - F.coalesce(F.lag(value).over(w), F.lit(0.0))).alias("delta"))


def ids(updates: DataFrame) -> DataFrame:
    return updates.select("row_id").distinct()


def exact_rows(updates: DataFrame, d: int) -> DataFrame:
    """The current matrix: (row_id, vec)."""
    return updates.groupBy("row_id").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("col_id") == j, F.col("delta"))), F.lit(0.0)) for j in range(d)]).alias("vec"))
