"""Values that a replay must not draw again: recorded results, times of new calls, generated keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window


def recorded(name: str, otherwise: Column) -> Column:
    """The value that the original run drew for black-box `name`; `otherwise` for calls that are new."""
    return F.coalesce(F.col("recorded")[name], otherwise)


def estimate_ts(history: DataFrame, at_idx: int) -> DataFrame:
    """(ts): the midpoint of the commit times around the place just before at_idx (one neighbour's time at either end)."""
    near = history.where(F.col("commit_idx").isin(at_idx - 1, at_idx)).select("commit_idx", F.unix_micros("ts").alias("us"))
    both = near.agg(F.max(F.when(F.col("commit_idx") == at_idx - 1, F.col("us"))).alias("a"), F.max(F.when(F.col("commit_idx") == at_idx, F.col("us"))).alias("b"))
    mid = F.floor((F.coalesce("a", "b") + F.coalesce("b", "a")) / 2).cast("long")
    return both.select(F.timestamp_micros(mid).alias("ts"))


def new_keys(rows: DataFrame, used: DataFrame, key: str, *order: str) -> DataFrame:
    """rows with a generated key that no statement of the whole history (used: key column) ever had."""
    top = used.agg(F.coalesce(F.max(key), F.lit(0)).alias("_top"))
    rank = F.row_number().over(Window.orderBy(*order))  # the new calls of one scenario, never the history
    return rows.crossJoin(F.broadcast(top)).withColumn(key, F.col("_top") + rank).drop("_top")
