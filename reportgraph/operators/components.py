"""Connected components of an edge table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reportgraph.sources.io import checkpointed


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def _to_smallest(pairs: DataFrame) -> DataFrame:
    """Each (u, v) with the smallest v of its u; the minimum is combined before its shuffle, the join splits hot u."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m"))
    return pairs.join(least, "u")


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """``(node, component)`` for every node of an undirected edge table; the component is its smallest node.

    Nulls and self loops are left out, repeated edges count once, an empty table gives an empty result.
    The graph is contracted towards the smallest neighbour in turns (every node's larger neighbours,
    then its smaller ones) until it consists of stars. The number of rounds grows with the logarithm
    of the diameter; each round's edges are checkpointed. Nothing but two numbers reaches the driver.
    """
    a, b = F.col(src), F.col(dst)
    e = edges.where(a.isNotNull() & b.isNotNull() & (a != b))
    e = checkpointed(e.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct())
    before = _state(e)
    for _ in range(max_rounds):
        if not before[0]:
            break
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _to_smallest(both).where("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()
        near = _to_smallest(large)
        small = near.select("u", F.col("m").alias("v")).unionByName(
            near.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        )
        e = checkpointed(small.where("u <> v").distinct())
        after = _state(e)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
        e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )
