"""The knowledge graph: type graph, full graph, queries, cliques and shortest paths."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reportgraph.operators.components import connected_components
from reportgraph.sources.io import checkpointed


def type_graph(relations: DataFrame, weight: str = "npmi") -> DataFrame:
    """Edges ``src, dst, weight`` between entity types, src < dst."""
    return relations.select(F.least("e1", "e2").alias("src"), F.greatest("e1", "e2").alias("dst"), F.col(weight).alias("weight"))


def full_graph(reports: DataFrame, mentions: DataFrame, relations: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes ``id, kind, label`` and edges ``src, dst, kind, weight`` of reports, teams, mentioned values, types and their relations."""
    value = F.concat_ws("=", "entity", "value")
    r, t, e, v = (lambda c, k=k: F.concat(F.lit(f"{k}:"), F.col(c).cast("string") if isinstance(c, str) else c) for k in ("report", "team", "type", "value"))
    node = lambda df, i, kind, label: df.select(i.alias("id"), F.lit(kind).alias("kind"), label.alias("label"))
    nodes = (
        node(reports, r("report_id"), "report", F.col("title")).unionByName(node(reports.select("team").distinct(), t("team"), "team", F.col("team")))
        .unionByName(node(mentions.select("entity").distinct(), e("entity"), "type", F.col("entity")))
        .unionByName(node(mentions.select("entity", "value").distinct(), v(value), "value", F.col("value")))
    )
    edge = lambda df, a, b, kind, w=F.lit(1.0): df.select(a.alias("src"), b.alias("dst"), F.lit(kind).alias("kind"), w.alias("weight"))
    edges = (
        edge(mentions.select("report_id", "entity", "value").distinct(), r("report_id"), v(value), "mentions")
        .unionByName(edge(reports, r("report_id"), t("team"), "handled by"))
        .unionByName(edge(mentions.select("entity", "value").distinct(), v(value), e("entity"), "is a"))
        .unionByName(edge(relations, e("e1"), e("e2"), "related", F.col("npmi")))
    )
    return nodes, edges


def shared_values(mentions: DataFrame, min_reports: int = 2) -> DataFrame:
    """Values that several reports mention, with their number and the first of them; a value's reports are counted, not gathered."""
    one = mentions.select("entity", "value", "report_id").distinct()
    return one.groupBy("entity", "value").agg(F.count("*").alias("reports"), F.min("report_id").alias("first_report")).where(F.col("reports") >= min_reports)


def match(edges: DataFrame, pattern: list[tuple[str, str, str]]) -> DataFrame:
    """Ways to fit a pattern of (variable, kind of edge, variable) into the full graph, one column for each variable.

    Each triple is an equi-join on the variables that those before it have; a triple without such is refused, and different
    variables stand for different nodes.
    """
    found = None
    for a, kind, b in pattern:
        one = edges.where(F.col("kind") == kind).select(F.col("src").alias(a), F.col("dst").alias(b)).distinct()
        if found is None:
            found = one
            continue
        known = [v for v in dict.fromkeys((a, b)) if v in found.columns]
        if not known:
            raise ValueError(f"{a} and {b} are not connected with what is before")
        new = [v for v in (a, b) if v not in known]
        before = found.columns
        found = found.join(one, known)
        for v in new:
            for w in before:
                found = found.where(F.col(v) != F.col(w))
    return found


def _both(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst", "weight").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))


def neighbors(edges: DataFrame, node: str) -> DataFrame:
    return _both(edges).where(F.col("src") == node).select(F.col("dst").alias("node"), "weight")


def degrees(edges: DataFrame) -> DataFrame:
    return _both(edges).groupBy(F.col("src").alias("node")).agg(F.count("*").alias("degree"), F.sum("weight").alias("weighted_degree"))


def components(edges: DataFrame) -> DataFrame:
    return connected_components(edges)


def triangles(edges: DataFrame) -> DataFrame:
    """``a, b, c`` in order: wedges of an edge table with src < dst, closed by a third edge."""
    e = edges.select("src", "dst")
    ab, bc, ac = e.toDF("a", "b"), e.toDF("b", "c"), e.toDF("a", "c")
    return ab.join(bc, "b").join(ac, ["a", "c"]).select("a", "b", "c")


def maximal_cliques(edges: DataFrame, min_size: int = 2) -> DataFrame:
    """``members, size, min_weight, mean_weight`` of all maximal cliques.

    Each vertex gets the edges among itself and its neighbours, and enumerates those maximal cliques of which it
    comes first; with all neighbours at hand, a clique found is maximal in the whole graph.
    """
    e = edges.select("src", "dst", "weight")
    both = _both(e)
    around = both.select(F.col("src").alias("v"), F.col("dst").alias("n"))
    star = both.select(F.col("src").alias("v"), F.col("src").alias("a"), F.col("dst").alias("b"), "weight")
    inner = around.join(e.toDF("n", "o", "weight"), "n").join(around.toDF("v", "o"), ["v", "o"]).select("v", F.col("n").alias("a"), F.col("o").alias("b"), "weight")

    def enumerate_cliques(key, pdf: pd.DataFrame) -> pd.DataFrame:
        v = key[0]
        near: dict = {}
        w: dict = {}
        for a, b, x in zip(pdf["a"], pdf["b"], pdf["weight"]):
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
            w[a, b] = w[b, a] = x
        out = []

        def grow(clique: list, may: set, done: set) -> None:
            if not may and not done:
                out.append(sorted(clique))
                return
            pivot = max(may | done, key=lambda u: len(near[u] & may))
            for u in sorted(may - near[pivot]):
                grow([*clique, u], may & near[u], done & near[u])
                may = may - {u}
                done = done | {u}

        later, earlier = {u for u in near[v] if u > v}, {u for u in near[v] if u < v}
        grow([v], later, earlier)
        rows = []
        for c in out:
            ws = [w[a, b] for i, a in enumerate(c) for b in c[i + 1 :]]
            rows.append((c, len(c), min(ws) if ws else None, sum(ws) / len(ws) if ws else None))
        return pd.DataFrame(rows, columns=["members", "size", "min_weight", "mean_weight"])

    kind = dict(edges.dtypes)["src"]
    got = star.unionByName(inner).groupBy("v").applyInPandas(enumerate_cliques, f"members array<{kind}>, size int, min_weight double, mean_weight double")
    return got.where(F.col("size") >= min_size)


def shortest_paths(edges: DataFrame, sources: DataFrame, metric: str = "hops", max_rounds: int = 100) -> DataFrame:
    """``source, target, hops, path, weights`` of a shortest path from each ``sources.source`` to all it reaches.

    'hops' counts edges, 'distance' adds 1 - weight. Ties: larger mean weight, then the path first in order. The frontier
    of all sources advances together; a round is a join with the edges and a minimum, checkpointed now and then.
    """
    both = _both(edges)
    cost = F.lit(1.0) if metric == "hops" else F.lit(1.0) - F.col("weight")
    both = both.select(F.col("src").alias("target"), F.col("dst").alias("next"), "weight", cost.alias("cost"))
    best = sources.select("source", F.col("source").alias("target"), F.lit(0.0).alias("dist"), F.array("source").alias("path"), F.array().cast("array<double>").alias("weights"))
    mean = lambda ws: F.when(F.size(ws) > 0, F.aggregate(ws, F.lit(0.0), lambda a, x: a + x) / F.size(ws)).otherwise(0.0)
    frontier = best
    for round_ in range(max_rounds):
        step = frontier.join(both, "target").where(~F.array_contains("path", F.col("next"))).select(
            "source", F.col("next").alias("target"), (F.col("dist") + F.col("cost")).alias("dist"), F.concat("path", F.array("next")).alias("path"), F.concat("weights", F.array("weight")).alias("weights")
        )
        key = lambda: F.struct(F.round("dist", 12).alias("d"), F.round(-mean(F.col("weights")), 12).alias("m"), F.col("path").alias("p"))
        marked = best.withColumn("old", F.lit(True)).unionByName(step.withColumn("old", F.lit(False)))
        won = marked.groupBy("source", "target").agg(F.min(F.struct(key().alias("k"), F.struct("dist", "path", "weights", "old").alias("r"))).alias("x")).select("source", "target", "x.r.*")
        won = checkpointed(won)
        frontier = won.where("not old").drop("old")
        best = won.drop("old")
        if frontier.isEmpty():
            break
    return best.select("source", "target", F.size("weights").alias("hops"), "path", "weights")
