"""Candidate pairs of name and value from patterns; extractors can be added by name."""

from __future__ import annotations

import functools
import re
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Extractor = Callable[[DataFrame], DataFrame]
_REGISTERED: dict[str, Extractor] = {}


def _pair(df: DataFrame, at: Column, width: int, pattern: str) -> DataFrame:
    """The halves before and after a place (from 1; 0 for none) of ``text``, if neither is empty."""
    # As a row of its own the place is found once; as an expression each use of it would find it again.
    rows = df.select("report_id", "sent_no", "text", F.explode(F.array(at)).alias("at")).where("at > 0")
    name = F.trim(F.substring("text", F.lit(1), F.col("at") - 1))
    value = F.trim(F.substring("text", F.col("at") + width, F.length("text")))
    rows = rows.withColumns({"name": name, "value": value, "pattern": F.lit(pattern)})
    return rows.where("length(name) > 0 and length(value) > 0").select("report_id", "sent_no", "name", "value", "pattern")


def key_value(df: DataFrame, separators: tuple[str, ...] = (":",), max_name_words: int = 6) -> DataFrame:
    """Name and value around a sentence's first separator.

    A separator within a URL (before ``//``) or a time of day (between digits) does not count, nor does one after
    more than ``max_name_words`` words. Sentences that hold a tab belong to the tables' pattern.
    """
    out = []
    for s in separators:
        mark = re.escape(s)
        free = rf"^(.*?)(?<![0-9](?={mark}[0-9])){mark}(?!//)"
        # The text before the separator and the separator itself, so nothing is found where there is no separator.
        at = F.length(F.regexp_extract("text", free, 0))
        rows = _pair(df.where(~F.col("text").contains("\t") & F.col("text").contains(s)), at - (len(s) - 1), len(s), "key_value" if s == ":" else f"key_value {s}")
        out.append(rows.where(F.size(F.split("name", " +")) <= max_name_words))
    return functools.reduce(DataFrame.unionByName, out)


def tables(df: DataFrame) -> DataFrame:
    """Rows of two-column tables, which cleaning has made lines with a tab."""
    return _pair(df, F.locate("\t", F.col("text")), 1, "table")


def register(name: str, extractor: Extractor) -> None:
    """Makes a further pattern known: from sentences to candidates."""
    _REGISTERED[name] = extractor


def emails(df: DataFrame) -> DataFrame:
    found = F.explode(F.regexp_extract_all("text", F.lit(r"[\w.+-]+@[\w-]+(?:\.[\w-]+)+"), F.lit(0)))
    return df.select("report_id", "sent_no", F.lit("email address").alias("name"), found.alias("value"), F.lit("email").alias("pattern"))


def secrets(df: DataFrame) -> DataFrame:
    """Runs of 40 hexadecimal digits, as access tokens have."""
    found = F.explode(F.regexp_extract_all("text", F.lit(r"\b[0-9a-f]{40}\b"), F.lit(0)))
    return df.select("report_id", "sent_no", F.lit("secret").alias("name"), found.alias("value"), F.lit("secret").alias("pattern"))


register("key_value", key_value)
register("table", tables)
register("email", emails)
register("secret", secrets)
register("equals", functools.partial(key_value, separators=("=",)))


def extract_all(df: DataFrame, names: tuple[str, ...] = ("key_value", "table")) -> DataFrame:
    return functools.reduce(DataFrame.unionByName, [_REGISTERED[n](df) for n in names])
