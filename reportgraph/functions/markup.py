"""Markup by a real parser, for nested tables and broken tags; the expressions in ``text`` are the fast way for plain ones."""

from __future__ import annotations

from html.parser import HTMLParser

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

BLOCKS = frozenset("p div br li ul ol h1 h2 h3 h4 h5 h6 tr table nav article section footer header title body head html".split())


class _Reader(HTMLParser):
    """Text, and tables as lists of rows of cells; a table inside a cell is a table of its own."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.out: list[str] = []
        self.open: list[dict] = []
        self.tables: list[list[list[str]]] = []
        self.skip = 0

    def handle_starttag(self, tag, attrs):
        if tag in ("script", "style"):
            self.skip += 1
        elif tag == "table":
            self.open.append({"rows": [], "cell": None})
        elif tag == "tr" and self.open:
            self.open[-1]["rows"].append([])
        elif tag in ("td", "th") and self.open:
            t = self.open[-1]
            if not t["rows"]:
                t["rows"].append([])
            t["rows"][-1].append("")
            t["cell"] = True
        if tag in BLOCKS and not self.open:
            self.out.append("\n")

    def handle_endtag(self, tag):
        if tag in ("script", "style"):
            self.skip = max(0, self.skip - 1)
        elif tag == "table" and self.open:
            self._close()
        elif tag in ("td", "th") and self.open:
            self.open[-1]["cell"] = None
        if tag in BLOCKS and not self.open:
            self.out.append("\n")

    def handle_data(self, data):
        if self.skip:
            return
        if not self.open:
            self.out.append(data)
        elif self.open[-1]["cell"] and self.open[-1]["rows"][-1]:
            self.open[-1]["rows"][-1][-1] += data

    def _close(self):
        rows = [[" ".join(c.split()) for c in r] for r in self.open.pop()["rows"] if r]
        self.tables.append(rows)
        if rows and not any(len(r) > 2 for r in rows):
            self.out.append("\n" + "\n".join("\t".join(r) for r in rows) + "\n")

    def finish(self):
        self.close()
        while self.open:
            self._close()
        return self


def read(html: str | None) -> _Reader:
    r = _Reader()
    r.feed(html or "")
    return r.finish()


def parsed_text(html: Column) -> Column:
    """Text without markup; tables of at most two columns as lines with a tab, wider ones dropped."""

    @F.pandas_udf(T.StringType())
    def run(h: pd.Series) -> pd.Series:
        return h.map(lambda x: "\n".join(p.strip(" ") for p in "".join(read(x).out).split("\n") if p.strip()))

    return run(html)


def parsed_rows(html: Column) -> Column:
    """Rows of two cells of tables that have no wider row."""

    @F.pandas_udf(T.ArrayType(T.StructType([T.StructField("name", T.StringType()), T.StructField("value", T.StringType())])))
    def run(h: pd.Series) -> pd.Series:
        return h.map(lambda x: [{"name": r[0], "value": r[1]} for t in read(x).tables if not any(len(r) > 2 for r in t) for r in t if len(r) == 2])

    return run(html)
