"""Labels without labelled data: entity types from frequent names, mentions, value types, tag sequences."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reportgraph.functions.text import TYPES, split_camel, tokenize, value_type
from reportgraph.operators.hot import join_hot
from reportgraph.sources.io import checkpointed

#: Fewer names than this may be broadcast.
BROADCAST_NAMES = 200_000

#: Words that begin a name without being part of it.
DETERMINERS = ("the", "a", "an", "this", "that", "my", "your", "his", "her", "its", "our", "their")


def clean_name(c: Column) -> Column:
    return F.lower(F.trim(F.regexp_replace(split_camel(c), " +", " ")))


def drop_noisy_names(df: DataFrame) -> DataFrame:
    """Candidates whose name has letters and blanks only, the name with its camel case parted and in lower case."""
    return df.where(F.col("name").rlike(r"^[\p{L} ]+$")).withColumn("name", clean_name(F.col("name")))


def name_ngrams(df: DataFrame, n_min: int = 1, n_max: int = 3, keep: tuple[str, ...] = ()) -> DataFrame:
    """``*keep, name, gram, n, place`` of each word sequence of a name that no determiner begins or ends."""
    words = F.split("name", " ")
    grams = F.flatten(
        F.transform(
            F.sequence(F.lit(n_min), F.lit(n_max)),
            lambda n: F.transform(
                F.when(F.size(words) >= n, F.sequence(F.lit(1), F.size(words) - n + 1)).otherwise(F.array().cast("array<int>")),
                lambda i: F.struct(F.array_join(F.slice(words, i, n), " ").alias("gram"), n.alias("n"), i.alias("place")),
            ),
        )
    )
    rows = df.select(*keep, "name", F.explode(grams).alias("g")).select(*keep, "name", "g.*")
    edge = F.array(*[F.lit(d) for d in DETERMINERS])
    return rows.where(~F.array_contains(edge, F.element_at(F.split("gram", " "), 1)) & ~F.array_contains(edge, F.element_at(F.split("gram", " "), -1)))


def gram_counts(candidates: DataFrame, n_min: int = 1, n_max: int = 3) -> DataFrame:
    """Candidates are counted by name before they are cut into grams, so a frequent name is cut once."""
    names = drop_noisy_names(candidates.groupBy("name").agg(F.count("*").alias("c")))
    return name_ngrams(names, n_min, n_max, keep=("c",)).groupBy("gram", "n").agg(F.sum("c").alias("freq"))


def top_k_types(candidates: DataFrame, k: int = 100, subsume: bool = True) -> DataFrame:
    """``gram, n, freq, rank`` of the k most frequent grams; ties go to longer, then alphabetically.

    With ``subsume`` a gram that occurs in a selected longer one as often as altogether is left out. The k
    rows are the only thing that is not distributed.
    """
    top = gram_counts(candidates).orderBy(F.desc("freq"), F.desc("n"), "gram").limit(k)
    if subsume:
        longer = top.select(F.col("gram").alias("long"), F.col("n").alias("ln"), F.col("freq").alias("lf"))
        inside = F.concat(F.lit(" "), F.col("long"), F.lit(" ")).contains(F.concat(F.lit(" "), F.col("gram"), F.lit(" ")))
        top = top.join(F.broadcast(longer), (F.col("n") < F.col("ln")) & (F.col("freq") == F.col("lf")) & inside, "left_anti")
    return top.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("freq"), F.desc("n"), "gram")))


def resolve_names(candidates: DataFrame, types: DataFrame) -> DataFrame:
    """``name, entity`` for each name: of the selected grams it holds the longest, then most frequent, then rightmost, then first by letter."""
    names = drop_noisy_names(candidates.select("name").distinct()).distinct()
    hits = name_ngrams(names).join(F.broadcast(types.select("gram", "freq")), "gram")
    # the first letter wins by the smallest gram, so its rank among equals is by negated order: take min over a struct of negated keys
    key = F.struct((-F.col("n")).alias("a"), (-F.col("freq")).alias("b"), (-F.col("place")).alias("c"), F.col("gram").alias("d"))
    return hits.groupBy("name").agg(F.min(key)["d"].alias("entity"))


def tag_patterns(candidates: DataFrame, types: DataFrame) -> DataFrame:
    """Mentions of all types in the patterns, in one pass: ``report_id, sent_no, entity, value``.

    The names are counted before they are broadcast; more than ``BROADCAST_NAMES`` are joined by a shuffle, hot ones in many tasks.
    Names are cleaned once each, not once for each candidate that has them.
    """
    counts = checkpointed(candidates.groupBy("name").agg(F.count("*").alias("n")))
    cleaned = drop_noisy_names(counts.withColumn("raw", F.col("name")))
    resolved = checkpointed(resolve_names(counts, types).join(cleaned, "name").select(F.col("raw").alias("name"), "entity", "n"))
    if resolved.count() < BROADCAST_NAMES:
        rows = candidates.join(F.broadcast(resolved.drop("n")), "name")
    else:
        rows = join_hot(candidates, resolved, "name", ["report_id", "sent_no"], "inner")
    return rows.select("report_id", "sent_no", "entity", "value")


def entity_value_types(mentions: DataFrame) -> DataFrame:
    """The most frequent value type of each entity (ties: the more specific), with its share."""
    counts = mentions.groupBy("entity", value_type(F.col("value")).alias("value_type")).agg(F.count("*").alias("c"))
    order = F.array_position(F.array(*[F.lit(t) for t in TYPES]), F.col("value_type"))
    best = counts.groupBy("entity").agg(F.min(F.struct((-F.col("c")).alias("c"), order.alias("o"), F.col("value_type").alias("t"))).alias("b"), F.sum("c").alias("freq"))
    return best.select("entity", F.col("b.t").alias("value_type"), (-F.col("b.c")).alias("support"), "freq")


#: A part that is one token whatever the way of cutting.
PLAIN = r"^(?:\p{Lu}?\p{Ll}+|\p{Lu}+|[0-9]+)\z"


def token_rows(sentences: DataFrame, tokens: str = "words", keep: tuple[str, ...] = ()) -> DataFrame:
    """``report_id, sent_no, *keep, tokens, starts, place``: tokens of sentences, whether a blank stands before each, and in which part between blanks it is.

    ``tokens``: 'words' parts camel case and signs, which stay as tokens, and keeps addresses and the like whole; 'no separators' is
    the same without signs; 'blanks' cuts at blanks only. A part without tokens stays as one.
    """
    parts = F.split("text", "[ \t]+")
    whole = F.transform(parts, lambda p: F.array(p))
    if tokens != "blanks":  # each part is cut once; a plain word or number is one token and needs no search
        cut = F.transform(parts, lambda p: F.when(p.rlike(PLAIN), F.array(p)).otherwise(tokenize(p, separators=tokens == "words")))
        whole = F.zip_with(parts, cut, lambda p, c: F.when(F.size(c) > 0, c).otherwise(F.array(p)))
    rows = sentences.select("report_id", "sent_no", *keep, whole.alias("parts"))
    return rows.select(
        "report_id", "sent_no", *keep, F.flatten("parts").alias("tokens"),
        F.flatten(F.transform("parts", lambda p: F.transform(p, lambda t, i: i == 0))).alias("starts"),
        F.flatten(F.transform("parts", lambda p, k: F.transform(p, lambda t: k))).alias("place"),
    )


def encode(sentences: DataFrame, mentions: DataFrame, types: DataFrame, scheme: str = "bio", tokens: str = "words", keep: tuple[str, ...] = ()) -> DataFrame:
    """``report_id, sent_no, *keep, tokens, starts, entity_tags, type_tags``: tags for both tasks, of equal length.

    ``mentions`` has ``begin`` and ``size`` in parts between blanks from 0, which ``token_rows`` cuts into tokens. Sentences
    without a mention have only outside tags.
    """
    # Texts are joined, which take less room than their tokens.
    return encode_spans(sentences.join(sentence_spans(mentions, types), ["report_id", "sent_no"], "left"), scheme, tokens, keep)


def sentence_spans(mentions: DataFrame, types: DataFrame) -> DataFrame:
    """``report_id, sent_no, spans``: the mentions of each sentence that has any, in order, with the value types of their entities."""
    typed = mentions.join(F.broadcast(types.select("entity", "value_type")), "entity")
    return typed.groupBy("report_id", "sent_no").agg(F.array_sort(F.collect_list(F.struct("begin", "size", "entity", "value_type"))).alias("spans"))


def encode_spans(sentences: DataFrame, scheme: str = "bio", tokens: str = "words", keep: tuple[str, ...] = ()) -> DataFrame:
    """``encode`` of sentences with a column ``spans``."""
    rows = token_rows(sentences, tokens, (*keep, "spans"))

    def tags_at(i: Column, first: Column) -> Column:
        """Both tags of a token, from one search of its span."""
        lead = lambda s: F.when((s["begin"] == i) & first, F.lit("B-")).otherwise(F.lit("I-")) if scheme == "bio" else F.lit("")
        hit = F.filter("spans", lambda s: (s["begin"] <= i) & (i < s["begin"] + s["size"]))
        return F.get(F.transform(hit, lambda s: F.struct(F.concat(lead(s), s["entity"]).alias("e"), F.concat(lead(s), s["value_type"]).alias("t"))), 0)

    rows = rows.withColumn("hits", F.when(F.col("spans").isNotNull(), F.zip_with("place", "starts", tags_at)))
    tags = lambda field: F.when(F.col("hits").isNull(), F.array_repeat(F.lit("O"), F.size("place"))).otherwise(F.transform("hits", lambda h: F.coalesce(h[field], F.lit("O"))))
    return rows.select("report_id", "sent_no", *keep, "tokens", "starts", tags("e").alias("entity_tags"), tags("t").alias("type_tags"))


def _edge(df: DataFrame, t: Column, share: float) -> int | None:
    """The smallest time up to which ``share`` of the rows lie (none without times).

    Rows are counted by time and sorted in ranges; a count of each range tells in which one the edge lies, and that one alone is added up.
    """
    counts = checkpointed(df.select(t.alias("t")).where("t IS NOT NULL").groupBy("t").agg(F.count("*").alias("n")).orderBy("t"))
    ranges = counts.groupBy(F.spark_partition_id().alias("p")).agg(F.sum("n").alias("n"), F.min("t").alias("lo"), F.max("t").alias("hi")).collect()
    rank, before = max(1, math.ceil(share * sum(r["n"] for r in ranges))), 0
    for r in sorted(ranges, key=lambda r: r["lo"]):
        if before + r["n"] >= rank:
            upto = F.sum("n").over(Window.orderBy("t")) + before
            return counts.where(F.col("t").between(r["lo"], r["hi"])).select("t", upto.alias("upto")).where(F.col("upto") >= rank).agg(F.min("t")).first()[0]
        before += r["n"]
    return None


def temporal_split(df: DataFrame, time_col: str, test_share: float = 0.2) -> DataFrame:
    """Adds ``part``: 'test' strictly after the time below which the other rows lie, else 'train'; null times train."""
    t = F.unix_micros(F.col(time_col).cast("timestamp"))
    edge = _edge(df, t, 1 - test_share)
    return df.withColumn("part", F.when(t > F.lit(edge).cast("long"), "test").otherwise("train"))
