"""Entity lists for title clusters, by path scores in the type graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from reportgraph.functions.vectors import euclidean
from reportgraph.operators.graph import shortest_paths


def cluster_entities(mentions: DataFrame, clusters: DataFrame, n: int = 5) -> DataFrame:
    """``cluster_id, rank, entity, freq``: the n most frequent entities of each cluster's reports (ties by letter); noise has none."""
    rows = mentions.join(clusters.where("cluster_id >= 0").select("report_id", "cluster_id"), "report_id")
    counts = rows.groupBy("cluster_id", "entity").agg(F.count("*").alias("freq"))
    w = Window.partitionBy("cluster_id").orderBy(F.desc("freq"), "entity")
    return counts.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n).select("cluster_id", "rank", "entity", "freq")


def frequency_only(mentions: DataFrame, clusters: DataFrame, n: int = 5) -> DataFrame:
    """The ranking to compare with: by frequency in the cluster alone."""
    return cluster_entities(mentions, clusters, n)


def primary(top: DataFrame, edges: DataFrame) -> DataFrame:
    """``cluster_id, entity``: of a cluster's top entities the first that the graph has; clusters without such are left out."""
    nodes = edges.select(F.col("src").alias("entity")).union(edges.select("dst")).distinct()
    return top.join(F.broadcast(nodes), "entity", "left_semi").groupBy("cluster_id").agg(F.min_by("entity", "rank").alias("entity"))


def relation_scores(primaries: DataFrame, edges: DataFrame, denominator: str = "edges", combine: str = "mean", metric: str = "hops") -> DataFrame:
    """``primary, entity, score``: over a shortest path the mean of its weights (over edges, or nodes), or their product; the primary itself has 1."""
    sources = primaries.select(F.col("entity").alias("source")).distinct()
    p = shortest_paths(edges, sources, metric)
    total = F.aggregate("weights", F.lit(0.0), lambda a, x: a + x)
    product = F.aggregate("weights", F.lit(1.0), lambda a, x: a * x)
    mean = total / (F.col("hops") + (0 if denominator == "edges" else 1))
    score = F.when(F.col("hops") == 0, 1.0).otherwise(mean if combine == "mean" else product)
    return p.select(F.col("source").alias("primary"), F.col("target").alias("entity"), score.alias("score"))


def top_k(primaries: DataFrame, scores: DataFrame, k: int = 5) -> DataFrame:
    """``cluster_id, rank, entity, score``, ties by letter."""
    rows = primaries.select("cluster_id", F.col("entity").alias("primary")).join(F.broadcast(scores), "primary")
    w = Window.partitionBy("cluster_id").orderBy(F.desc("score"), "entity")
    return rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("cluster_id", "rank", "entity", "score")


def centroids(points: DataFrame, clusters: DataFrame, vec_col: str = "vector") -> DataFrame:
    """``cluster_id, centre``: the mean vector of each cluster."""
    rows = points.join(clusters.where("cluster_id >= 0"), "id").select("cluster_id", F.posexplode(vec_col).alias("i", "x"))
    m = rows.groupBy("cluster_id", "i").agg(F.avg("x").alias("x"))
    return m.groupBy("cluster_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("centre"))


def nearest_cluster(points: DataFrame, centres: DataFrame, vec_col: str = "vector", max_distance: float | None = None) -> DataFrame:
    """``id, cluster_id, distance``: the nearest centre (ties: the smaller id); farther than ``max_distance`` is refused. Centres are broadcast after a count."""
    if centres.count() > 100_000:
        raise ValueError("too many centres to broadcast")
    rows = points.select("id", F.col(vec_col).alias("v")).crossJoin(F.broadcast(centres))
    d = euclidean(F.col("v"), F.col("centre"))
    best = rows.withColumn("d", d).groupBy("id").agg(F.min(F.struct("d", "cluster_id")).alias("b")).select("id", "b.cluster_id", F.col("b.d").alias("distance"))
    return best if max_distance is None else best.where(F.col("distance") <= max_distance)
