"""A join whose frequent keys are dealt over many tasks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

HOT_ROWS, HOT_SHARE = 1000, 10_000


def spread_join(rows: DataFrame, table: DataFrame, key: str, total: int, spread: Column, how: str = "inner") -> DataFrame:
    """``rows`` joined with ``table`` (one row per ``key``; its column n: how many of the ``total`` rows have it).

    A hot key has more than ``HOT_ROWS`` rows and a ``HOT_SHARE``-th of all, so there are at most
    ``HOT_SHARE`` of them at any size; only they are broadcast. Their rows are dealt by ``spread``
    over as many parts as they have multiples of that number, and the table's row goes to each part.
    Rows without a key match nothing and are dealt at large.
    """
    many = max(HOT_ROWS, total // HOT_SHARE)
    hot = table.where(F.col("n") > many).select(F.col(key).alias("_hot"), F.ceil(F.col("n") / many).cast("int").alias("_parts"))
    part = F.when(rows[key].isNull(), F.pmod(spread, F.lit(HOT_SHARE))).otherwise(F.coalesce(F.pmod(spread, F.col("_parts")), F.lit(0))).cast("int")
    left = rows.join(F.broadcast(hot), rows[key] == F.col("_hot"), "left").withColumn("_part", part).drop("_hot", "_parts")
    parts = F.when(F.col("n") > many, F.ceil(F.col("n") / many)).otherwise(1).cast("int")
    right = table.withColumn("_part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("n")
    return left.join(right, [key, "_part"], how).drop("_part")
