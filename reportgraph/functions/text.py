"""Cleaning and typing of report text, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Patterns of the value types, the complex ones first.
GUID = r"^\{?[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}\}?$"
IP = r"^(?:(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[1-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[1-9]?[0-9])(?:/[0-9]{1,2})?$"
URI = r"^(?:[A-Za-z][A-Za-z0-9+.-]*://\S+|/\S+/\S*|www\.\S+)$"
NUMERIC = r"^[+-]?(?:[0-9]+|[0-9]{1,3}(?:,[0-9]{3})+)(?:\.[0-9]+)?$"
TYPES = ("GUID", "IP", "URI", "Boolean", "Numeric", "Alphabetical", "Alphanumeric", "Non-Alphanumeric", "Other")
_CASES = (
    ("GUID", GUID), ("IP", IP), ("URI", URI), ("Boolean", r"^(?:[Tt]rue|[Ff]alse|TRUE|FALSE|[Yy]es|[Nn]o)$"), ("Numeric", NUMERIC),
    ("Alphabetical", r"^[\p{L} ]*\p{L}[\p{L} ]*$"), ("Alphanumeric", r"^[\p{L}0-9 ]*(?:\p{L}[\p{L} ]*[0-9]|[0-9][0-9 ]*\p{L})[\p{L}0-9 ]*$"), ("Non-Alphanumeric", r"^[^\p{L}\p{N}]+$"),
)


def value_type(c: Column) -> Column:
    """One of nine types of a value; null and the empty string have type Other."""
    v = F.trim(c)
    out = None
    for name, pattern in _CASES:
        out = F.when(v.rlike(pattern), name) if out is None else out.when(v.rlike(pattern), name)
    return out.otherwise("Other")


def value_type_sql(v: str, cast: str = "") -> str:
    """The same as SQL for engines that have ``regexp_matches``."""
    return "CASE " + " ".join(f"WHEN regexp_matches(trim({v}), '{p}') THEN '{n}'" for n, p in _CASES) + " ELSE 'Other' END"


def squeeze(c: Column) -> Column:
    return F.trim(F.regexp_replace(c, r"\s+", " "))


TABLE, ROW, CELL = r"(?is)<table\b.*?</table>", r"(?is)<tr\b.*?</tr>", r"(?is)<t[dh]\b[^>]*>(.*?)</t[dh]>"


def _tables(html: Column) -> Column:
    return F.regexp_extract_all(html, F.lit(TABLE), F.lit(0))


def _is_wide(table: Column) -> Column:
    return F.exists(F.regexp_extract_all(table, F.lit(ROW), F.lit(0)), lambda r: F.size(F.regexp_extract_all(r, F.lit(CELL), F.lit(1))) > 2)


def drop_wide_tables(html: Column) -> Column:
    """Without tables of which any row has more than two cells. Tables inside tables need the parser's way."""
    return F.aggregate(F.filter(_tables(html), _is_wide), html, lambda text, t: F.replace(text, t, F.lit("")))


def two_column_rows(html: Column) -> Column:
    """``array<struct<name,value>>`` of the rows of two cells."""
    cells = F.transform(F.flatten(F.transform(_tables(html), lambda t: F.regexp_extract_all(t, F.lit(ROW), F.lit(0)))), lambda r: F.regexp_extract_all(r, F.lit(CELL), F.lit(1)))
    return F.transform(F.filter(cells, lambda c: F.size(c) == 2), lambda c: F.struct(c[0].alias("name"), c[1].alias("value")))


def tables_as_lines(html: Column) -> Column:
    """Two-column tables turned into lines of name, tab and value."""

    def lines(t: Column) -> Column:
        rows = F.filter(F.transform(F.regexp_extract_all(t, F.lit(ROW), F.lit(0)), lambda r: F.regexp_extract_all(r, F.lit(CELL), F.lit(1))), lambda c: F.size(c) == 2)
        return F.array_join(F.transform(rows, lambda c: F.concat(c[0], F.lit("\t"), c[1])), "\n")

    return F.aggregate(_tables(html), html, lambda text, t: F.replace(text, t, F.concat(F.lit("\n"), lines(t), F.lit("\n"))))


def strip_markup(html: Column) -> Column:
    """Text of markup: scripts, styles and comments go, block tags end lines, the common entities are read."""
    t = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->", " ")
    t = F.regexp_replace(t, r"(?i)</?(?:p|div|br|li|ul|ol|h[1-6]|tr|table|nav|article|section|footer|header|title|body|head|html)\b[^>]*>", "\n")
    t = F.regexp_replace(t, "<[^>]+>", "")
    for entity, sign in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&middot;", "·"), ("&copy;", "©"), ("&amp;", "&")):
        t = F.replace(t, F.lit(entity), F.lit(sign))
    return t


def plain(c: Column) -> Column:
    """All of cleaning but the split: wide tables dropped, others as lines, markup stripped where there is any."""
    html = tables_as_lines(drop_wide_tables(c))
    return F.when(c.contains("<"), strip_markup(html)).otherwise(c)


def sentences(df: DataFrame, text_col: str = "description", id_col: str = "report_id", clean: bool = True) -> DataFrame:
    """``report_id, sent_no, text``: one row for each line that is not blank, numbered from 0 within its report; null texts have none."""
    body = plain(F.col(text_col)) if clean else F.col(text_col)
    lines = F.filter(F.transform(F.split(body, "\n"), lambda s: F.trim(F.when(s.contains("  "), F.regexp_replace(s, " +", " ")).otherwise(s))), lambda s: s != "")
    return df.select(F.col(id_col).alias("report_id"), F.posexplode(lines).alias("sent_no", "text"))


#: URLs, GUIDs, addresses and e-mails stay whole; then words, numbers and single signs.
TOKEN = r"[A-Za-z][A-Za-z0-9+.-]*://\S+|[0-9a-fA-F]{8}(?:-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}|[\w.+-]+@[\w-]+(?:\.[\w-]+)+|[0-9]{1,3}(?:\.[0-9]{1,3}){3}|\p{L}+|[0-9]+|[^\s\p{L}0-9]"


def split_camel(c: Column) -> Column:
    """A blank between a small and a capital letter, and before the last capital of a run that a small letter follows."""
    return F.regexp_replace(c, r"(?<=\p{Ll})(?=\p{Lu})|(?<=\p{Lu})(?=\p{Lu}\p{Ll})", " ")


def tokenize(c: Column, camel: bool = True, separators: bool = True) -> Column:
    whole = F.regexp_extract_all(c, F.lit(TOKEN), F.lit(0))
    if camel:  # only a capital that is not the first letter can begin a word
        whole = F.flatten(F.transform(whole, lambda t: F.when(t.rlike(r"^\p{L}+\p{Lu}\p{L}*$"), F.split(split_camel(t), " ")).otherwise(F.array(t))))
    return whole if separators else F.filter(whole, lambda t: t.rlike(r"[\p{L}0-9]"))


def windows(df: DataFrame, tokens_col: str = "tokens", max_len: int = 300, stride: int = 250) -> DataFrame:
    """Rows of at most ``max_len`` tokens; longer lists give overlapping windows, so no token is lost."""
    n = F.size(tokens_col)
    last = F.when(n <= max_len, 0).otherwise(F.ceil((n - max_len) / F.lit(stride)).cast("int"))
    rows = df.withColumn("window", F.explode(F.sequence(F.lit(0), last)))
    return rows.withColumn(tokens_col, F.slice(tokens_col, F.col("window") * stride + 1, F.lit(max_len)))
