"""Removal of repeated passages by hashing normalised units of lines.

A line's units are its sentences; case, signs and the width of blanks do not count. A long sentence is cut after
words that their own hash marks, so two sentences that are equal in part have units in common. Equal units are
grouped over all documents by a 128-bit digest and ranked by document and place; the first stays.
A run of neighbouring units that all repeat earlier ones is removed if it has ``min_words`` words, so a
passage is found inside lines too, while short stock phrases stay. Offsets of what is removed are
those of the original text.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from reportgraph.llm.worker import slices, turn
from reportgraph.operators.hot import join_hot
from reportgraph.sources.io import checkpointed

MIN_WORDS = 20
#: A unit ends with a sentence before white space, or with its line; blanks after it belong to it.
UNIT_END = re.compile(r"[.!?]+[\"')\]]*(?=\s|$)[^\S\n]*|\n+")
WORD = re.compile(r"[^\W_]+")
#: Sentences of more words than this are cut, after one word in ``CUT_SHARE``, or after as many words again without such.
LONG_SENTENCE, CUT_SHARE = 24, 10
MEMO = 100_000
SPANS = "array<struct<start:int,end:int>>"


class _CutWords(dict):
    """Whether a sentence may be cut after a word."""

    def __missing__(self, word: str) -> bool:
        if len(self) > MEMO:
            self.clear()
        self[word] = got = zlib.crc32(word.encode("utf-8", "surrogatepass")) % CUT_SHARE == 0
        return got


_CUTS = _CutWords()


def _digest(words: list[str]) -> bytes:
    return xxhash.xxh3_128_digest(" ".join(words).encode("utf-8", "surrogatepass"))


def units(text: str) -> list[tuple[int, int, int, bytes]]:
    """``(start, end, words, digest)`` of each unit that has words; offsets are code points."""
    out, at = [], 0
    for end in (*(m.end() for m in UNIT_END.finditer(text)), len(text)):
        words = [w.lower() for w in WORD.findall(text, at, end)]
        if len(words) > LONG_SENTENCE:
            begin, own = at, []
            for m, w in zip(WORD.finditer(text, at, end), words):
                own.append(w)
                if _CUTS[w] or len(own) == LONG_SENTENCE:
                    out.append((begin, m.end(), len(own), _digest(own)))
                    begin, own = m.end(), []
            if own:
                out.append((begin, end, len(own), _digest(own)))
        elif words:
            out.append((at, end, len(words), _digest(words)))
        at = end
    return out


def unit_table(docs: DataFrame) -> DataFrame:
    """``(row, doc, unit, start, end, words, digest)`` of all units; ``row`` is a digest of id and text."""
    kind = dict(docs.dtypes)["__doc"]
    own = next(f.type for f in to_arrow_schema(docs.schema) if f.name == "__doc")
    types = [pa.int64(), own, *[pa.int32()] * 4, pa.binary()]
    names = ["row", "doc", "unit", "start", "end", "words", "digest"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn("substring dedup")
        for b in slices(batches):
            out: list[tuple] = []
            for r, i, text in zip(*(b.column(k).to_pylist() for k in range(3))):
                out.extend((r, i, n, *u) for n, u in enumerate(units(text)))
                if len(out) > 20_000:
                    yield pack(out)
                    out = []
            if out:
                yield pack(out)
        _CUTS.clear()

    def pack(out: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names=names)

    return docs.select("__row", "__doc", "__text").mapInArrow(run, f"row long, doc {kind}, unit int, start int, end int, words int, digest binary")


def repeated_units(docs: DataFrame) -> DataFrame:
    """``(row, doc, units)``: for each row with such, its units that repeat an earlier one, in order.

    The earliest of a group is found by a minimum that is combined before the shuffle, and only groups of two
    or more take part in the join back, in which hot digests are dealt to many tasks.
    """
    all_units = unit_table(docs)
    rank = F.struct(F.col("doc").isNull().alias("last"), "doc", "row", "unit")
    groups = all_units.groupBy("digest").agg(F.count("*").alias("n"), F.min(rank).alias("first")).where("n > 1")
    groups = checkpointed(groups.select("digest", "n", F.col("first.doc").alias("first_doc"), F.col("first.row").alias("first_row"), F.col("first.unit").alias("first_unit")))
    again = join_hot(all_units, groups, "digest", ["row"], "inner")
    again = again.where((F.col("row") != F.col("first_row")) | (F.col("unit") != F.col("first_unit")) | ~F.col("doc").eqNullSafe(F.col("first_doc")))
    return again.groupBy("row", "doc").agg(F.array_sort(F.collect_set(F.struct("unit", "start", "end", "words"))).alias("units"))


def long_runs(rows: DataFrame, min_words: int) -> DataFrame:
    """``(row, doc, spans)``: half-open ranges of the runs of neighbouring ``units`` that have enough words."""
    kind = dict(rows.dtypes)["doc"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(2)
            unit, start, end, words = (np.asarray(x, np.int64) for x in lists.flatten().flatten())
            owner = np.repeat(np.arange(b.num_rows), np.diff(lists.offsets.to_numpy()))
            first = np.flatnonzero((np.diff(owner, prepend=-1) != 0) | (np.diff(unit, prepend=-2) != 1))
            if not len(first):
                continue
            last = np.append(first[1:], len(unit)) - 1
            keep = np.add.reduceat(words, first) >= min_words
            count = np.bincount(owner[first[keep]], minlength=b.num_rows)
            spans = pa.StructArray.from_arrays([pa.array(start[first[keep]], pa.int32()), pa.array(end[last[keep]], pa.int32())], names=["start", "end"])
            out = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(count)]), pa.int32()), spans)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), out], names=["row", "doc", "spans"]).filter(pa.array(count > 0))

    return rows.mapInArrow(run, f"row long, doc {kind}, spans {SPANS}")


def dedup_passages(docs: DataFrame, min_words: int = MIN_WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All rows of ``docs`` and their columns, with the text less repeated passages, and ``removed_spans`` of the original text.

    Earlier is the smaller id (nulls last), then the smaller digest of the text, then the place in the text.
    A null text stays null. Rows of equal id and text are one document, and so each keeps what the other
    keeps; an empty table gives no rows. A document left without text stays, with the empty text. A column ``removed_spans`` of
    ``docs`` is replaced.
    """
    text = F.coalesce(F.col(f"`{text_col}`"), F.lit(""))
    row = F.xxhash64(F.col(f"`{id_col}`"), text)
    spans = long_runs(repeated_units(docs.select(row.alias("__row"), F.col(f"`{id_col}`").alias("__doc"), text.alias("__text"))), min_words)
    names = [c for c in docs.columns if c != "removed_spans"]
    full = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("__d"), row.alias("__row"), F.col(f"`{id_col}`").alias("__doc"))
    joined = full.join(spans, (full["__row"] == spans["row"]) & full["__doc"].eqNullSafe(spans["doc"]), "left")
    joined = joined.select("__d", F.coalesce("spans", F.array().cast(SPANS)).alias("removed_spans"))
    body = F.col(f"__d.`{text_col}`")
    # What stands between the removed ranges, by column functions.
    starts = F.concat(F.array(F.lit(0)), F.transform("removed_spans", lambda s: s["end"]))
    ends = F.concat(F.transform("removed_spans", lambda s: s["start"]), F.array(F.length(body)))
    kept = F.array_join(F.zip_with(starts, ends, lambda a, b: F.substring(body, a + 1, b - a)), "")
    cleaned = F.when(F.size("removed_spans") > 0, kept).otherwise(body)
    return joined.select(*[(cleaned.alias(c) if c == text_col else F.col(f"__d.`{c}`").alias(c)) for c in names], "removed_spans")
