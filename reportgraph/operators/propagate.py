"""Label propagation: values seen in the patterns tag their other occurrences."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reportgraph.sources.io import checkpointed

#: A dictionary of fewer values than this may be broadcast; it is counted first.
BROADCAST_VALUES = 200_000


def value_dictionary(mentions: DataFrame, types: DataFrame, max_value_tokens: int = 5, min_value_len: int = 3, min_support: int = 1) -> DataFrame:
    """``value, tokens, entity, support``: for each value the entity under which it occurs most (ties alphabetically).

    Values of Boolean entities, those of more than ``max_value_tokens`` words and very short ones are left out,
    and so are entities whose median value is as long (descriptions).
    """
    words = F.size(F.split("value", " +"))
    described = mentions.groupBy("entity").agg(F.percentile_approx(words, 0.5).alias("m")).where(F.col("m") > max_value_tokens)
    plain = types.where("value_type <> 'Boolean'").join(described, "entity", "left_anti").select("entity")
    counts = mentions.join(F.broadcast(plain), "entity").where((words <= max_value_tokens) & (F.length("value") >= min_value_len) & ~F.lower("value").isin("true", "false"))
    counts = counts.groupBy("value", "entity").agg(F.count("*").alias("c"))
    best = counts.groupBy("value").agg(F.min(F.struct((-F.col("c")).alias("c"), F.col("entity").alias("e"))).alias("b"))
    best = best.select("value", F.size(F.split("value", " +")).alias("tokens"), F.col("b.e").alias("entity"), (-F.col("b.c")).alias("support"))
    return best.where(F.col("support") >= min_support)


def _bare(c: Column) -> Column:
    """Without signs at the end."""
    return F.rtrim(c, F.lit(",.;!?"))


def occurrences(sentences: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Word windows that may be a value of the dictionary; signs at the end of a window do not count.

    Each word is a window by itself. Longer ones are cut out where a value of several words begins as they do and is as long: the first words
    of such values are counted, and looked up by a broadcast while they are few.
    """
    firsts = dictionary.where("tokens > 1").groupBy(_bare(F.element_at(F.split("value", " "), 1)).alias("first")).agg(F.array_sort(F.collect_set("tokens")).alias("sizes"))
    firsts = checkpointed(firsts)
    rows = sentences.select("report_id", "sent_no", F.split("text", "[ \t]+").alias("w"))
    words = rows.select("report_id", "sent_no", "w", F.posexplode(F.transform("w", _bare)).alias("begin", "first"))
    longer = _bare(F.array_join(F.slice("w", F.col("begin") + 1, F.col("size")), " "))
    if firsts.count() < BROADCAST_VALUES:
        sizes = F.concat(F.array(F.lit(1)), F.coalesce("sizes", F.array().cast("array<int>")))
        windows = words.join(F.broadcast(firsts), "first", "left").select("report_id", "sent_no", "w", "begin", "first", F.explode(sizes).alias("size"))
        windows = windows.where(F.col("begin") + F.col("size") <= F.size("w"))
        return windows.select("report_id", "sent_no", "begin", "size", F.when(F.col("size") == 1, F.col("first")).otherwise(longer).alias("value"))
    ones = words.select("report_id", "sent_no", "begin", F.lit(1).alias("size"), F.col("first").alias("value"))
    places = words.drop("w").join(firsts, "first").select("report_id", "sent_no", "begin", F.explode("sizes").alias("size"))
    # The words of a sentence are fetched once for all its places.
    places = places.groupBy("report_id", "sent_no").agg(F.collect_list(F.struct("begin", "size")).alias("p"))
    windows = rows.join(places, ["report_id", "sent_no"]).select("report_id", "sent_no", "w", F.explode("p").alias("p")).select("report_id", "sent_no", "w", "p.*")
    windows = windows.where(F.col("begin") + F.col("size") <= F.size("w"))
    return ones.unionByName(windows.select("report_id", "sent_no", "begin", "size", longer.alias("value")))


def longest_first(spans: Column) -> Column:
    """Spans (begin, size, ...) without overlap: longest first, then leftmost."""
    ordered = F.array_sort(spans, lambda a, b: F.when(a["size"] != b["size"], b["size"] - a["size"]).otherwise(a["begin"] - b["begin"]))
    none = F.filter(ordered, lambda s: F.lit(False))
    free = F.aggregate(ordered, none, lambda kept, s: F.when(F.exists(kept, lambda k: (k["begin"] < s["begin"] + s["size"]) & (s["begin"] < k["begin"] + k["size"])), kept).otherwise(F.concat(kept, F.array(s))))
    return F.when(F.size(spans) < 2, spans).otherwise(free)


def propagate(sentences: DataFrame, dictionary: DataFrame, seeds: DataFrame) -> DataFrame:
    """Mentions ``report_id, sent_no, begin, size, entity, value`` in sentences that hold no seed.

    The dictionary is broadcast while it is small, which is checked; a larger one is joined by a shuffle, whose hot values
    Spark may split. Overlapping values: the longest first, then the leftmost.
    """
    small = dictionary.count() < BROADCAST_VALUES
    free = sentences.join(seeds.select("report_id", "sent_no"), ["report_id", "sent_no"], "left_anti")
    table = dictionary.select("value", "entity")
    hits = occurrences(free, dictionary).join(F.broadcast(table) if small else table, "value")
    groups = hits.groupBy("report_id", "sent_no").agg(longest_first(F.collect_list(F.struct("begin", "size", "entity", "value"))).alias("spans"))
    return groups.select("report_id", "sent_no", F.explode("spans").alias("s")).select("report_id", "sent_no", "s.*")


def seed_places(seeds: DataFrame, sentences: DataFrame) -> DataFrame:
    """Places of seed values in their sentences: a seed's value is the end of its sentence."""
    n, w = F.size(F.split("value", "[ \t]+")), F.size(F.split("text", "[ \t]+"))
    return seeds.join(sentences, ["report_id", "sent_no"]).select("report_id", "sent_no", (w - n).alias("begin"), n.alias("size"), "entity", "value")
