"""Measures: precision at rank, tag scores, differences, routing and engagement."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TYPE_RANKS = (1, 5, 10, 20, 35, 50, 75, 100)
PAIR_RANKS = (*range(1, 146, 8), 150)


def precision_at(ranked: DataFrame, ranks: tuple[int, ...]) -> DataFrame:
    """``n, hits, precision`` at each rank up to the number of rows; ``ranked`` has ``rank`` from 1 and ``is_valid``."""
    at = ranked.select(F.explode(F.array(*[F.lit(n) for n in ranks])).alias("n"), "rank", F.col("is_valid").cast("int").alias("v"))
    got = at.groupBy("n").agg(F.sum(F.when(F.col("rank") <= F.col("n"), F.col("v"))).alias("hits"), F.count("*").alias("rows"))
    return got.where("n <= rows").select("n", "hits", (F.col("hits") / F.col("n")).alias("precision"))


def precision_drop(curve: DataFrame, n: int = 100) -> DataFrame:
    return curve.where(F.col("n") == n).select("n", (1 - F.col("precision")).alias("precision_drop"))


def per_type(tags: DataFrame) -> DataFrame:
    """``tag, tp, fp, fn, precision, recall, f1, support`` from rows (gold, pred); O counts as no tag, undefined shares as 0."""
    rows = tags.select(F.explode(F.array(F.struct(F.col("gold").alias("tag"), F.lit(1).alias("g"), (F.col("pred") == F.col("gold")).cast("int").alias("hit")), F.struct(F.col("pred").alias("tag"), F.lit(0).alias("g"), F.lit(0).alias("hit")))).alias("x")).select("x.*").where("tag <> 'O'")
    c = rows.groupBy("tag").agg(F.sum("hit").alias("tp"), F.sum("g").alias("support"), F.sum(1 - F.col("g")).alias("given"))
    part = lambda a, b: F.coalesce(F.try_divide(F.col(a).cast("double"), F.col(b)), F.lit(0.0))
    c = c.withColumns({"precision": part("tp", "given"), "recall": part("tp", "support")})
    f1 = F.coalesce(F.try_divide(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")), F.lit(0.0))
    return c.select("tag", "tp", (F.col("given") - F.col("tp")).alias("fp"), (F.col("support") - F.col("tp")).alias("fn"), "precision", "recall", f1.alias("f1"), "support")


def averages(scores: DataFrame) -> DataFrame:
    """Unweighted means over tags that occur, and F1 weighted by support."""
    s = scores.where("support > 0")
    return s.agg(F.avg("precision").alias("macro_precision"), F.avg("recall").alias("macro_recall"), F.avg("f1").alias("macro_f1"), (F.sum(F.col("f1") * F.col("support")) / F.sum("support")).alias("weighted_f1"))


def error_examples(gold: DataFrame, pred: DataFrame, limit: int = 50) -> DataFrame:
    """False positives and negatives by place: ``report_id, sent_no, begin, gold, pred, kind``, the first ``limit``."""
    k = ["report_id", "sent_no", "begin"]
    rows = gold.select(*k, F.col("entity").alias("gold")).join(pred.select(*k, F.col("entity").alias("pred")), k, "full")
    rows = rows.where(~F.col("gold").eqNullSafe(F.col("pred")))
    kind = F.when(F.col("gold").isNull(), "false positive").when(F.col("pred").isNull(), "false negative").otherwise("confused")
    return rows.withColumn("kind", kind).orderBy(*k).limit(limit)


def span_prf(gold: DataFrame, pred: DataFrame) -> DataFrame:
    """Exact-span precision, recall and F1 over all mentions."""
    k = ["report_id", "sent_no", "begin", "size", "entity"]
    both = gold.select(*k, F.lit(1).alias("g")).join(pred.select(*k, F.lit(1).alias("p")), k, "full")
    c = both.agg(F.sum("g").alias("gold"), F.sum("p").alias("pred"), F.count(F.when(F.col("g").isNotNull() & F.col("p").isNotNull(), 1)).alias("tp"))
    p, r = F.try_divide(F.col("tp"), F.col("pred")), F.try_divide(F.col("tp"), F.col("gold"))
    return c.select("gold", "pred", "tp", p.alias("precision"), r.alias("recall"), F.try_divide(2 * p * r, p + r).alias("f1"))


def delta_pct(a: Column, b: Column, kind: str = "relative") -> Column:
    """From a to b in percent: 'relative' to a, or 'symmetric', to the mean of both."""
    return 100 * (b - a) / a if kind == "relative" else 200 * (b - a) / (a + b)


def accuracy(df: DataFrame, gold: str = "label", pred: str = "prediction") -> DataFrame:
    return df.agg(F.avg((F.col(gold) == F.col(pred)).cast("double")).alias("accuracy"), F.count("*").alias("rows"))


def reassignment_rate(history: DataFrame, item: str, time: str, team: str, tie: str) -> DataFrame:
    """Share of items whose team changed, and of steps that changed it."""
    w = Window.partitionBy(item).orderBy(time, tie)
    steps = history.withColumn("before", F.lag(team).over(w))
    moved = (F.col("before").isNotNull() & (F.col("before") != F.col(team))).cast("int")
    items = steps.withColumn("moved", moved).groupBy(item).agg(F.sum("moved").alias("moves"), F.count("*").alias("steps"))
    return items.agg(F.count("*").alias("items"), F.avg((F.col("moves") > 0).cast("double")).alias("reassigned_share"), (F.sum("moves") / F.sum("steps")).alias("move_share"))


def time_to_engage(events: DataFrame, start: str = "error", engage: str = "login") -> DataFrame:
    """For each user the mean seconds from a ``start`` event to the next ``engage`` event of that user."""
    # Read from the end, the next is the last one seen, so the frame only grows.
    w = Window.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("event_id")).rowsBetween(Window.unboundedPreceding, -1)
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    rows = events.withColumn("next", F.last(F.when(F.col("event_type") == engage, t), ignorenulls=True).over(w))
    return rows.where((F.col("event_type") == start) & F.col("next").isNotNull()).groupBy("user_id").agg(F.count("*").alias("incidents"), F.avg((F.col("next") - t) / 1e6).alias("mean_seconds"))


def cluster_summary(clusters: DataFrame, gold: str) -> DataFrame:
    """Clusters, share of noise (-1), and share of rows in their cluster's largest class."""
    c = clusters.groupBy("cluster_id", gold).agg(F.count("*").alias("n"))
    per = c.groupBy("cluster_id").agg(F.sum("n").alias("n"), F.max("n").alias("top"))
    inside = F.col("cluster_id") >= 0
    return per.agg(F.count(F.when(inside, 1)).alias("clusters"), (F.coalesce(F.sum(F.when(~inside, F.col("n"))), F.lit(0)) / F.sum("n")).alias("noise_share"), (F.sum(F.when(inside, F.col("top"))) / F.sum(F.when(inside, F.col("n")))).alias("purity"))
