"""Pairs of entity types that occur together, and measures of how much more than by chance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pairs(mentions: DataFrame, scope: str = "sentence") -> DataFrame:
    """``e1, e2, f_joint`` with e1 < e2: in how many sentences (or reports) both types occur.

    Pairs are made within a sentence's set of types, so there is no self-join; their counts are combined before the shuffle.
    """
    keys = ["report_id", "sent_no"] if scope == "sentence" else ["report_id"]
    sets = mentions.groupBy(*keys).agg(F.array_sort(F.collect_set("entity")).alias("es")).where(F.size("es") > 1)
    rows = sets.select(F.posexplode("es").alias("i", "e1"), "es").select("e1", F.explode(F.slice("es", F.col("i") + 2, F.size("es"))).alias("e2"))
    return rows.groupBy("e1", "e2").agg(F.count("*").alias("f_joint"))


def frequencies(mentions: DataFrame, count: str = "mention") -> DataFrame:
    """``entity, f``: mentions, or sentences that hold one (``count='sentence'``)."""
    rows = mentions if count == "mention" else mentions.select("entity", "report_id", "sent_no").distinct()
    return rows.groupBy("entity").agg(F.count("*").alias("f"))


def with_frequencies(joint: DataFrame, freqs: DataFrame) -> DataFrame:
    """Adds f1, f2 and the total; there are no more frequencies than selected types, so they are broadcast."""
    total = freqs.agg(F.sum("f").alias("total"))
    one = lambda e, f: F.broadcast(freqs.select(F.col("entity").alias(e), F.col("f").alias(f)))
    return joint.join(one("e1", "f1"), "e1").join(one("e2", "f2"), "e2").join(F.broadcast(total))


def score(rows: DataFrame, measure: str = "npmi") -> DataFrame:
    """Adds ``measure`` from f1, f2, f_joint and total: 'pmi', 'npmi' (PMI over -ln of the joint share) or 'mi' (averaged over presence and absence)."""
    n = F.col("total").cast("double")
    f1, f2, f12 = (F.col(c).cast("double") for c in ("f1", "f2", "f_joint"))
    pmi = F.ln(f12 * n / (f1 * f2))
    if measure == "pmi":
        return rows.withColumn("pmi", pmi)
    if measure == "npmi":
        return rows.withColumn("npmi", F.when(f12 >= n, 1.0).otherwise(pmi / -F.ln(f12 / n)))
    cells = ((f12, f1, f2), (f1 - f12, f1, n - f2), (f2 - f12, n - f1, f2), (n - f1 - f2 + f12, n - f1, n - f2))
    total = F.lit(0.0)
    for joint, a, b in cells:
        total = total + F.when((joint > 0) & (a > 0) & (b > 0), joint / n * F.ln(joint * n / (a * b))).otherwise(0.0)
    return rows.withColumn("mi", total)


def keep(rows: DataFrame, min_score: float = 0.0, measure: str = "npmi") -> DataFrame:
    """Without pairs whose score is below ``min_score``."""
    return rows.where(F.col(measure) >= min_score)


def independent_or_better(rows: DataFrame) -> DataFrame:
    """The same as ``keep(..., 0)`` in whole numbers, without logarithms: f_joint * total >= f1 * f2."""
    d = lambda c: F.col(c).cast("decimal(19,0)")
    return rows.where(d("f_joint") * d("total") >= d("f1") * d("f2"))
