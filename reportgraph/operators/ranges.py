"""Splitting a table into ordered ranges of a key, without a global sort."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

INTEGERS = ("tinyint", "smallint", "int", "bigint")
#: Ranges beyond the shuffle partitions are only for evenness; so many are enough.
EVEN_RANGES = 4096


def range_edges(df: DataFrame, key: str, per_partition: int = 8, least_rows: int = 64) -> list:
    """Ascending inner edges that cut ``key`` (whole numbers or strings) into about equal ranges.

    One scan of the key alone for its number of rows and one for the edges; the driver gets one edge for each shuffle partition, or up to
    ``per_partition`` of them while those are fewer than ``EVEN_RANGES``. Edges of strings come from a sample by hash,
    of about 20 keys for each edge; they only decide how even the ranges are.
    """
    partitions = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    n = max(partitions, min(per_partition * partitions, EVEN_RANGES))
    rows = df.agg(F.count(key)).first()[0]
    n = max(1, min(n, rows // least_rows))
    if n < 2:
        return []
    if dict(df.dtypes)[key] in INTEGERS:
        got = df.agg(F.percentile_approx(key, [i / n for i in range(1, n)], max(10_000, 20 * n))).first()[0]
        return sorted({int(x) for x in got or []})
    every = max(1, rows // (20 * n))
    some = df.where(F.col(key).isNotNull()).select(F.col(key).cast("string").alias("k")).where(F.pmod(F.xxhash64("k"), F.lit(every)) == 0)
    some = sorted((r["k"] for r in some.select("k").distinct().collect()), key=lambda k: k.encode("utf-8"))
    return [some[i * len(some) // n] for i in sorted({i for i in range(1, n) if i * len(some) // n > (i - 1) * len(some) // n})]


def _array(values: list) -> Column:
    if isinstance(values[0], int):
        return F.expr(f"array({', '.join(f'{x}L' if x > -(1 << 63) else 'bigint(-9223372036854775808)' for x in values)})")
    return F.array(*[F.lit(x) for x in values])


def range_of(key: Column, edges: list) -> Column:
    """Number of edges below ``key`` (-1 for null), found in blocks of about the root of their number."""
    if not edges:
        return F.when(key.isNull(), F.lit(-1)).otherwise(F.lit(0))
    size = max(1, math.isqrt(len(edges)))
    blocks = [edges[i : i + size] for i in range(0, len(edges), size)]

    def below(values: Column) -> Column:
        return F.size(F.filter(values, lambda x: x < key))

    firsts = _array([b[0] for b in blocks])
    table = F.array(*[_array(b) for b in blocks])
    block = below(firsts)
    inner = (block - 1) * size + below(F.element_at(table, F.greatest(block, F.lit(1))))
    return F.when(key.isNull(), F.lit(-1)).when(block == 0, F.lit(0)).otherwise(inner)
