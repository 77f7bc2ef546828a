"""Mixing sources to target weights by Sainte-Laguë apportionment of equal-token blocks."""

from __future__ import annotations

import functools
import math
import operator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from reportgraph.sources.io import checkpointed

MAX_REPEATS = 3


def sainte_lague(weights: list[float], seats: int) -> list[int]:
    """Seats by the highest quotients weight/(2k+1); equal quotients go to the earlier weight.

    The divisor that deals out all seats is found by bisection, so the work does not grow with the
    number of seats; the last few seats go by quotient.
    """
    total = sum(weights)
    if seats <= 0 or total <= 0:
        return [0] * len(weights)
    lo, hi = 0.0, seats / total + (len(weights) + 1) / total  # seats for each unit of weight: too few, enough
    got = lambda x: [math.floor(w * x + 0.5) for w in weights]
    for _ in range(200):
        mid = (lo + hi) / 2
        if sum(got(mid)) <= seats:
            lo = mid
        else:
            hi = mid
    out = got(lo)
    while sum(out) < seats:
        k = max(range(len(weights)), key=lambda i: (weights[i] / (2 * out[i] + 1), -i))
        out[k] += 1
    return out


def capped_targets(sizes: list[int], weights: list[float], total: float, cap: float = MAX_REPEATS) -> list[float]:
    """Shares of ``total`` by weight, at most ``cap`` times the size; what is over is shared again by weight."""
    out, open_ = [0.0] * len(sizes), set(range(len(sizes)))
    rest = float(total)
    while open_:
        unit = rest / sum(weights[i] for i in open_)
        full = {i for i in open_ if weights[i] * unit > cap * sizes[i]}
        for i in full or open_:
            out[i] = float(cap * sizes[i]) if full else weights[i] * unit
        if not full:
            break
        rest -= sum(out[i] for i in full)
        open_ -= full
    return out


def shard_words(sizes: list[int], words: int, block: int) -> list[int]:
    """Words to take from each shard, ``words`` altogether: whole blocks by Sainte-Laguë, then what shards too small for theirs leave.

    What is over goes to the shards in order, as far as they have room.
    """
    blocks = sainte_lague([float(n) for n in sizes], words // block)
    out = [min(k * block, n) for k, n in zip(blocks, sizes)]
    rest = words - sum(out)
    for i, n in enumerate(sizes):
        more = min(rest, n - out[i])
        out[i] += more
        rest -= more
    return out


def mix(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    weights: tuple[float, ...] = (1.0, 2.0, 3.0),
    block_tokens: int = 64,
    seed: int = 42,
    max_shards: int = 1 << 14,
    shard_tokens: int = 1 << 16,
) -> DataFrame:
    """Which words of each document a mix to target weights takes.

    Returns ``doc_id, source, size, source_size, target, passes, spans, taken``: the whole document
    ``passes`` times and, besides, the half-open word ranges ``spans``.

    Sources in order of code points (null last) weigh as ``weights`` repeats. A source's target in whole
    blocks comes from Sainte-Laguë over all sources, and is then rounded to words. It is met by whole passes over the source; the
    rest is apportioned over the source's shards by the same rule, and in a shard, whose documents lie in
    a seeded order, the blocks of lowest seeded hash are taken, the last of them in part. A hot source has as many more shards.
    The driver holds a number for each source and for each of at most ``max_shards`` shards.
    Documents of equal id are ordered by text hash; empty texts have size 0 and nothing is taken.
    """
    spark = docs.sparkSession
    size = F.regexp_count(F.coalesce(F.col(text_col), F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("bigint")
    sized = docs.select(
        F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), size.alias("size"),
        F.xxhash64(F.col(id_col), F.lit(seed)).alias("h"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("th"),
    )
    sized = checkpointed(sized)
    sources = sorted(sized.groupBy("source").agg(F.sum("size").alias("n")).collect(), key=lambda r: (r["source"] is None, (r["source"] or "").encode("utf-8")))
    sizes = [r["n"] for r in sources]
    total = sum(sizes)
    w = [weights[i % len(weights)] for i in range(len(sources))]
    targets = capped_targets(sizes, w, total)
    seats = sainte_lague(targets, round(sum(targets) / block_tokens))
    # Blocks are too coarse for a small source; the words by which they miss a target are added or left off.
    odd = [round(t) - k * block_tokens for t, k in zip(targets, seats)]
    quota = [k * block_tokens + o for k, o in zip(seats, odd)]
    passes = [q // n if n else 0 for q, n in zip(quota, sizes)]
    rests = [q - p * n for q, p, n in zip(quota, passes, sizes)]
    per_shard = max(shard_tokens, math.ceil(total / max_shards) if total else 1)
    plan = spark.createDataFrame(
        [(r["source"], n, t, p, k, max(1, math.ceil(n / per_shard))) for r, n, t, p, k in zip(sources, sizes, targets, passes, rests)] or [],
        "s string, source_size long, target double, passes long, rest long, shards int",
    )
    rows = sized.join(F.broadcast(plan), F.col("source").eqNullSafe(F.col("s")), "inner").withColumn("shard", F.pmod("h", F.col("shards")).cast("int"))
    if len(sources) > 1 << 20:
        raise ValueError("more than 2**20 sources")
    shard_sizes = rows.groupBy("source", "shard", "rest").agg(F.sum("size").alias("n")).collect()
    by_source: dict = {}
    for r in sorted(shard_sizes, key=lambda r: r["shard"]):
        by_source.setdefault((r["source"], r["rest"]), []).append(r)
    dealt = [(s, r["shard"], q) for (s, rest), rs in by_source.items() for r, q in zip(rs, shard_words([r["n"] for r in rs], rest, block_tokens))]
    quotas = spark.createDataFrame(dealt or [], "qs string, qshard int, words long")

    order = Window.partitionBy("source", "shard").orderBy("h", "doc_id", "th")
    placed = rows.withColumn("end", F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0))).withColumn("begin", F.col("end") - F.col("size"))
    b = F.lit(block_tokens)
    # The blocks of a shard in seeded order; of the last one taken, only the words still due. The short last block comes last of all.
    blocks = (
        rows.groupBy("source", "shard").agg(F.sum("size").alias("n"))
        .join(F.broadcast(quotas), F.col("source").eqNullSafe(F.col("qs")) & (F.col("shard") == F.col("qshard")))
        .where("n > 0 and words > 0")
        .select("source", "shard", "words", F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("n") - 1) / b))).alias("block"), "n")
    )
    turn = Window.partitionBy("source", "shard").orderBy((F.col("n") < (F.col("block") + 1) * b), F.xxhash64("shard", "block", F.lit(seed + 1)), "block")
    chosen = blocks.withColumn("due", F.col("words") - (F.row_number().over(turn) - 1) * b).where("due > 0")
    chosen = chosen.select("source", "shard", "block", F.least(F.col("due"), b).alias("due"))
    # A document touches a run of blocks; the run is joined block by block and its ranges gathered per document.
    touch = placed.where("size > 0 and rest > 0").select(
        "doc_id", "th", "source", "shard", "begin", "end",
        F.explode(F.sequence(F.floor(F.col("begin") / b), F.floor((F.col("end") - 1) / b))).alias("block"),
    )
    chosen = chosen.select(F.col("source").alias("cs"), F.col("shard").alias("csh"), F.col("block").alias("cb"), "due")
    part = touch.join(chosen, F.col("source").eqNullSafe(F.col("cs")) & (F.col("shard") == F.col("csh")) & (F.col("block") == F.col("cb"))).select(
        F.col("doc_id").alias("pd"), F.col("th").alias("pt"), F.col("source").alias("ps"), F.col("begin").alias("pb"),
        F.struct((F.greatest("begin", F.col("block") * b) - F.col("begin")).alias("start"), (F.least("end", F.col("block") * b + F.col("due")) - F.col("begin")).alias("end")).alias("span"),
    ).where("span.start < span.end")
    part = part.groupBy("pd", "pt", "ps", "pb").agg(F.array_sort(F.collect_list("span")).alias("spans"))
    same = [F.col(x).eqNullSafe(F.col(y)) for x, y in (("doc_id", "pd"), ("th", "pt"), ("source", "ps"), ("begin", "pb"))]
    out = placed.join(part, functools.reduce(operator.and_, same), "left").select(
        "doc_id", F.col("th").alias("text_hash"), "source", "size", "source_size", "target", "passes",
        F.coalesce("spans", F.array().cast("array<struct<start:bigint,end:bigint>>")).alias("spans"),
    )
    more = F.aggregate("spans", F.lit(0).cast("bigint"), lambda a, s: a + s["end"] - s["start"])
    return out.withColumn("taken", F.col("passes") * F.col("size") + more)


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The documents of the mix, with the columns of ``docs``: each text as often and as far as the mix takes it, joined by newlines.

    Rows of equal id and text come as one row with what is taken from all of them.
    """
    m = mix(docs, **options).where("taken > 0").groupBy(F.col("doc_id").alias("mid"), F.col("text_hash").alias("mth")).agg(
        F.sum("passes").alias("times"), F.array_sort(F.flatten(F.collect_list("spans"))).alias("spans")
    )
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("d"))
    text = F.coalesce(F.col("d.text"), F.lit(""))
    rows = rows.withColumns({"id": F.col("d.doc_id"), "th": F.xxhash64(text)}).dropDuplicates(["id", "th"])
    rows = rows.join(m, F.col("id").eqNullSafe(F.col("mid")) & (F.col("th") == F.col("mth")))
    words = F.regexp_extract_all(text, F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))
    whole = F.array_repeat(text, F.col("times").cast("int"))
    some = F.when(F.size("spans") > 0, F.transform("spans", lambda s: F.array_join(F.slice(words, (s["start"] + 1).cast("int"), (s["end"] - s["start"]).cast("int")), " "))).otherwise(F.array().cast("array<string>"))
    rows = rows.select("d", F.array_join(F.concat(whole, some), "\n").alias("taken"))
    new = {"text": F.col("taken"), "n_chars": F.length("taken").cast("bigint")}
    return rows.select(*[new.get(c, F.col(f"d.`{c}`")).alias(c) for c in docs.columns])
