"""Serving: entities of a report as JSON, on request, by stream, or to other modules."""

from __future__ import annotations

import json
import math
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.types import DoubleType, StringType

from reportgraph.functions import text as T
from reportgraph.operators import labeling, patterns
from reportgraph.tagger import train
from reportgraph.tagger.model import Tagger


def extract(reports: DataFrame, types: DataFrame, text_col: str = "description") -> DataFrame:
    """Mentions of known types in the patterns of new reports."""
    return labeling.tag_patterns(patterns.extract_all(T.sentences(reports, text_col)), types)


def extract_by_model(reports: DataFrame, model: Tagger, text_col: str = "description", tokens: str = "words") -> DataFrame:
    """Mentions that a trained tagger finds in new reports, in their patterns and in free text; a map, so it runs on streams as on tables."""
    return train.text_mentions(T.sentences(reports, text_col), model, tokens)


def extract_json(mentions: DataFrame) -> DataFrame:
    """``report_id, entities`` as a JSON list of entity and value, in order of place."""
    rows = mentions.groupBy("report_id").agg(F.array_sort(F.collect_list(F.struct("sent_no", "entity", "value"))).alias("m"))
    return rows.select("report_id", F.to_json(F.transform("m", lambda x: F.struct(x["entity"].alias("entity"), x["value"].alias("value")))).alias("entities"))


def by_id(reports: DataFrame, types: DataFrame | None, report_id: int, model: Tagger | None = None) -> DataFrame:
    """The manual trigger: the entities of one report, by the tagger if one is given, else by the patterns."""
    one = reports.where(F.col("report_id") == report_id)
    return extract_json(extract_by_model(one, model) if model else extract(one, types))


def feed(mentions: DataFrame, required: tuple[str, ...]) -> DataFrame:
    """Reports that have all types a diagnostic module needs, with one value of each (the first by letter)."""
    rows = mentions.where(F.col("entity").isin(*required)).groupBy("report_id").agg(F.countDistinct("entity").alias("n"), *[F.min(F.when(F.col("entity") == e, F.col("value"))).alias(e.replace(" ", "_")) for e in required])
    return rows.where(F.col("n") == len(required)).drop("n")


def auto(stream: DataFrame, teams: tuple[str, ...], model: Tagger | None = None) -> DataFrame:
    """The automatic trigger for the reports of enabled teams: the tagger's mentions, or without one the key-value candidates.

    It has no state, so it runs on streams as on tables.
    """
    own = stream.where(F.col("team").isin(*teams))
    if model:
        return extract_by_model(own, model)
    return patterns.key_value(T.sentences(own, "description"))


def text_pairs(text: str | None) -> Iterator[tuple[str, str]]:
    """Candidate pairs of one text."""
    for line in (text or "").split("\n"):
        m = re.match(r"^([^:\t]+?)\s*:(?!//)\s*(\S.*)$", line)
        if m:
            yield m[1].strip(), m[2].strip()


@udtf(returnType="name: string, value: string")
class ExtractEntities:
    """Table function: candidate pairs of one text."""

    def eval(self, text: str):
        yield from text_pairs(text)


@F.pandas_udf(StringType())
def tag_json(text: pd.Series) -> pd.Series:
    """Candidate pairs of each text as a JSON list."""
    return text.map(lambda t: json.dumps([{"name": n, "value": v} for n, v in text_pairs(t)], ensure_ascii=False, separators=(",", ":")))


@F.pandas_udf(DoubleType())
def npmi_of(a: pd.Series, b: pd.Series) -> float:
    """Aggregate of two Boolean columns: how much more than by chance both are true in one row, from -1 to 1; null if one never is."""
    n, f1, f2, both = len(a), int(a.sum()), int(b.sum()), int((a & b).sum())
    if not f1 or not f2:
        return None
    if not both:
        return -1.0
    return 1.0 if both == n else math.log(both * n / (f1 * f2)) / -math.log(both / n)


def register(spark: SparkSession) -> None:
    """SQL functions: values' types, camel case, tokens and markup as expressions that are inlined, JSON of a text, an aggregate, and the table function."""
    spark.udtf.register("extract_entities", ExtractEntities)
    spark.udf.register("tag_json", tag_json)
    spark.udf.register("npmi_of", npmi_of)
    spark.sql(rf"CREATE OR REPLACE TEMPORARY FUNCTION tokenize(s STRING) RETURNS ARRAY<STRING> RETURN regexp_extract_all(s, r'{T.TOKEN}', 0)")
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION strip_markup(s STRING) RETURNS STRING RETURN trim(regexp_replace(regexp_replace(regexp_replace(s, r'(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->', ' '), r'<[^>]+>', ' '), r'\s+', ' '))")
    cases = " ".join(f"WHEN trim(s) RLIKE r'{p}' THEN '{n}'" for n, p in T._CASES)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION value_type(s STRING) RETURNS STRING RETURN CASE {cases} ELSE 'Other' END")
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION split_camel(s STRING) RETURNS STRING RETURN regexp_replace(s, r'(?<=\p{Ll})(?=\p{Lu})|(?<=\p{Lu})(?=\p{Lu}\p{Ll})', ' ')")
