"""Document fingerprints: sums of wide vectors hashed from paragraphs, modulo powers of two.

A paragraph (a line of the text) is hashed to a vector of 64-bit words. The fingerprint of a
text is the sum of its paragraphs' vectors, each word modulo a power of two, so that

* the order of paragraphs does not matter, their number of occurrences does;
* a paragraph is inserted or deleted by adding or subtracting its vector (``insert``, ``delete``);
* fingerprints of parts add up to that of the whole (``combine``).

The first words are dense digests and decide equality. The others sum the lengths of the paragraph's phrases
in lanes; two texts' lanes are compared by correlation, which is near the share of common text.
All of it is column expressions; there is no Python on the executors.
"""

from __future__ import annotations

import functools

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reportgraph.operators.ranges import range_edges, range_of

EXACT_WORDS = 4
#: Lanes of 31 bits: no text is long enough to wrap one.
LANE_WORDS = 40
LANES, LANE_BITS = 2, 31
GROUPS = 4
EXACT_MASK = (1 << 62) - 1
LANE_MASK = (1 << LANES * LANE_BITS) - 1
#: Phrases end at blanks after any sign but these small letters, about every third word.
PHRASE_END = r"(?<=[^b-mp-z\s])[ \t]+"
#: A phrase longer than this, as in scripts without blanks, is cut after some signs, about one in six, or after 16 without such.
LONG_PHRASE = 32
PIECE = r"(?s).{0,15}?[aeio0-3A-D,.;\u3001\u3002\uff0c\u4e00-\u50ff\u5b00-\u5dff\u6800-\u6aff\u7500-\u77ff\u8200-\u84ff\u8f00-\u91ff]|.{1,16}"
#: Paragraphs shorter than the second count by triples of signs, those as long as the first by phrases; between them by both.
SHORT = (64, 96)


def vector(text: str) -> Column:
    """The fingerprint of a text column as ``array<bigint>``; null counts as the empty text, which has one empty paragraph.

    Sums are masked at each step; both sides stay below 2**62, so none overflows. Lists are bound to variables, so each
    text is split once. A phrase is a hash, which gives its lane, and its length; phrases are first dealt to ``GROUPS`` of lanes.
    """
    t = f"coalesce(`{text}`, '')"
    exact = [f"aggregate(s.paragraphs, 0L, (a, p) -> (a + (xxhash64(p, {k}) & {EXACT_MASK}L)) & {EXACT_MASK}L)" for k in range(EXACT_WORDS)]
    # Of a hash, the low bits give the group, then the word of the group, then the lane of the word.
    per = LANE_WORDS // GROUPS
    lanes = []
    for g in range(LANE_WORDS):
        own = f"pmod(shiftright(f.h, 8), {per}) = {g // GROUPS}"
        one = f"shiftleft(f.w, {LANE_BITS} * cast(shiftright(f.h, 2) & {LANES - 1} as int))"
        lanes.append(f"aggregate(g[{g % GROUPS}], 0L, (a, f) -> if({own}, (a + {one}) & {LANE_MASK}L, a))")
    cut = f"flatten(transform(filter(split(p, r'{PHRASE_END}'), x -> x != ''), x -> if(length(x) > {LONG_PHRASE}, regexp_extract_all(x, r'{PIECE}', 0), array(x))))"
    phrases = f"transform(if(length(p) >= {SHORT[0]}, {cut}, cast(array() as array<string>)), x -> named_struct('h', xxhash64(x), 'w', cast(length(x) as bigint)))"
    triples = f"transform(if(length(p) between 1 and {SHORT[1] - 1}, sequence(1, greatest(length(p) - 2, 1)), cast(array() as array<int>)), i -> named_struct('h', xxhash64(substring(p, i, 3)), 'w', 1L))"
    lists = f"transform(array(split({t}, r'\n')), l -> named_struct('paragraphs', l, 'features', flatten(transform(l, p -> concat({phrases}, {triples})))))"
    groups = f"array({', '.join(f'filter(s.features, f -> (f.h & {GROUPS - 1}) = {k})' for k in range(GROUPS))})"
    return F.expr(f"transform({lists}, s -> concat(array({', '.join(exact)}), transform(array({groups}), g -> array({', '.join(lanes)}))[0]))[0]")


def _masks() -> Column:
    return F.array(*[F.lit(EXACT_MASK)] * EXACT_WORDS, *[F.lit(LANE_MASK)] * LANE_WORDS)


def combine(a: Column, b: Column) -> Column:
    """Fingerprint of the paragraphs of both."""
    return F.zip_with(F.zip_with(a, b, lambda x, y: x + y), _masks(), lambda x, m: x.bitwiseAND(m))


insert = combine


def delete(a: Column, b: Column) -> Column:
    """Fingerprint of ``a`` without the paragraphs of ``b``."""
    return F.zip_with(F.zip_with(a, b, lambda x, y: x - y), _masks(), lambda x, m: x.bitwiseAND(m))


def as_text(fingerprint: Column) -> Column:
    """Hexadecimal digits of all words."""
    return F.array_join(F.transform(fingerprint, lambda x: F.lpad(F.hex(x), 16, "0")), "")


def _lanes(fingerprint: Column) -> Column:
    words = F.slice(fingerprint, EXACT_WORDS + 1, LANE_WORDS)
    lane = (1 << LANE_BITS) - 1
    return F.flatten(F.transform(words, lambda x: F.array(*[F.shiftright(x, LANE_BITS * i).bitwiseAND(F.lit(lane)).cast("double") for i in range(LANES)])))


def moments(lanes: Column) -> tuple[Column, Column]:
    return tuple(F.aggregate(lanes, F.lit(0.0), f) for f in (lambda a, x: a + x, lambda a, x: a + x * x))


def likeness(df: DataFrame, pairs: dict[str, tuple[str, str]]) -> DataFrame:
    """Adds a likeness from 0 to 1 for each pair of fingerprint columns: 1 if equal, else their lanes' correlation, 0 at least.

    A text without phrases, or with the same sum in each lane, is like no other text.
    """
    used = sorted({c for pair in pairs.values() for c in pair})
    df = df.withColumns({f"__l_{c}": _lanes(F.col(c)) for c in used})
    df = df.withColumns({f"__{k}_{c}": m for c in used for k, m in zip("sq", moments(F.col(f"__l_{c}")))})
    n = float(LANE_WORDS * LANES)
    for name, (a, b) in pairs.items():
        dot = F.aggregate(F.zip_with(f"__l_{a}", f"__l_{b}", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
        var = functools.reduce(lambda x, y: x * y, [F.col(f"__q_{c}") - F.col(f"__s_{c}") * F.col(f"__s_{c}") / n for c in (a, b)])
        r = F.when(var > 1e-9, (dot - F.col(f"__s_{a}") * F.col(f"__s_{b}") / n) / F.sqrt(var)).otherwise(0.0)
        df = df.withColumn(name, F.when(F.col(a) == F.col(b), 1.0).otherwise(F.least(F.lit(1.0), F.greatest(F.lit(0.0), r))))
    return df.drop(*[x for x in df.columns if x.startswith(("__l_", "__s_", "__q_"))])


def with_next(docs: DataFrame, id_col: str, payload: list[str]) -> DataFrame:
    """Each row's ``payload`` columns and, as ``next_*``, those of the row with the next smaller id; after the last, of the first.

    Rows are dealt by ordered ranges of the id, and the first row of each range is copied to the
    range above it, so a range is complete in itself: one shuffle of the rows, no global sort.
    Null ids come last; rows of one id are ordered by their payload.
    """
    edges = range_edges(docs, id_col)
    rows = docs.select(F.col(id_col).alias("__id"), *payload).withColumn("__range", range_of(F.col("__id"), edges))
    heads = docs.select(F.col(id_col).alias("__id")).groupBy(range_of(F.col("__id"), edges).alias("__range")).agg(F.max("__id").alias("head"))
    heads = sorted(heads.collect(), reverse=True)  # a row for each range
    above = {r["__range"]: heads[i - 1]["__range"] for i, r in enumerate(heads)}  # of the highest: the lowest
    if not heads:
        return rows.select(F.col("__id").alias(id_col), *payload, *[F.col(c).alias(f"next_{c}") for c in payload])
    table = docs.sparkSession.createDataFrame([(r["__range"], r["head"], above[r["__range"]]) for r in heads], f"__at int, __head {dict(docs.dtypes)[id_col]}, __above int")
    rows = rows.join(F.broadcast(table), (F.col("__at") == F.col("__range")) & F.col("__head").eqNullSafe(F.col("__id")), "left")
    places = F.when(F.col("__at").isNull(), F.array(F.struct(F.col("__range").alias("r"), F.lit(0).alias("copy")))).otherwise(
        F.array(F.struct(F.col("__range").alias("r"), F.lit(0).alias("copy")), F.struct(F.col("__above").alias("r"), F.lit(1).alias("copy")))
    )
    rows = rows.select("__id", *payload, F.explode(places).alias("__place"))
    w = Window.partitionBy("__place.r").orderBy("__place.copy", F.col("__id").desc_nulls_last(), *payload)
    rows = rows.select("__id", *payload, "__place", *[F.lead(c).over(w).alias(f"next_{c}") for c in payload])
    return rows.where("__place.copy = 0").select(F.col("__id").alias(id_col), *payload, *[f"next_{c}" for c in payload])


def document_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprints of every text and of the text with its last third replaced by the head of the next document.

    Null texts count as empty. Rows of equal id are ordered by text; null ids come last; an empty table gives no rows.
    """
    base = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).withColumn("print", vector("text"))
    rows = with_next(base, "doc_id", ["text", "print"])
    rows = rows.withColumn("n_chars", F.length("text").cast("bigint"))
    cut = F.floor(F.col("n_chars") / 3).cast("int")
    rows = rows.withColumn("edited", F.concat(F.substring("text", F.lit(1), F.col("n_chars").cast("int") - cut), F.substring("next_text", F.lit(1), cut)))
    rows = rows.select("doc_id", "n_chars", "print", "next_print", F.sha2("edited", 256).alias("edited_sha256"), vector("edited").alias("edited_print"))
    rows = likeness(rows, {"near_edited": ("print", "edited_print"), "near_next": ("print", "next_print")})
    return rows.select("doc_id", "n_chars", "edited_sha256", as_text(F.col("print")).alias("fingerprint"), as_text(F.col("edited_print")).alias("edited_fingerprint"), "near_edited", "near_next")
