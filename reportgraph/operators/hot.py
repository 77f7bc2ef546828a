"""Joins by keys of which one may hold a third of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LEAST_HOT = 1000
#: A table of a few numbers a row may be broadcast if it has no more rows than this, which is some 60 MB.
BROADCAST_ROWS = 1_000_000


def small_or_not(table: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """``table`` marked for broadcast if it has at most ``most`` rows, which are counted; a larger one is joined by a shuffle."""
    return F.broadcast(table) if table.limit(most + 1).count() <= most else table


def join_hot(rows: DataFrame, table: DataFrame, key: str, spread: list[str], how: str = "left", count: str = "n") -> DataFrame:
    """``rows`` joined with ``table`` by ``key``; a key with more rows than an even share of a task is dealt to several.

    ``table`` has one row for each key, with the number of rows that have it as ``count``, and is read three times, so it should be
    written. Rows of a hot key are dealt by hash of their columns ``spread``, over as many salts as the key
    has such shares, and its row of ``table`` is repeated for each. Hot keys are fewer than the tasks, and they alone are broadcast.
    Null keys match nothing.
    """
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    total = table.agg(F.sum(count)).first()[0] or 0
    share = max(LEAST_HOT, total // tasks)
    times = F.ceil(F.col(count) / share).cast("int")
    hot = table.where(F.col(count) > share).select(F.col(key).alias("__hot"), times.alias("__times"))
    rows = rows.join(F.broadcast(hot), rows[key] == F.col("__hot"), "left")
    salt = F.coalesce(F.pmod(F.xxhash64(*spread), F.col("__times")).cast("int"), F.lit(0))
    rows = rows.withColumn("__salt", salt).drop("__hot", "__times")
    table = table.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.greatest(times, F.lit(1)) - 1)))
    return rows.join(table, [key, "__salt"], how).drop("__salt")
