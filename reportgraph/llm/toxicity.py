"""Toxicity by a factorization machine over hashed terms.

Besides a weight for each term the machine has a short vector for each, and a pair of terms in a text adds the
product of their vectors; so an insult together with the mention of a group can weigh more
than both alone. Terms are words and the beginnings of longer words, hashed. The machine has a column for each term that
tells the classes apart by itself, and for each that does so only together with another one.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reportgraph.llm.training import MAX_LABELLED, held_out, labelled_sample
from reportgraph.sources.io import checkpointed

HASH_BITS = 24
#: Longer words also give their first so many letters as a term, so that forms of one stem are learned together.
STEM = 6
#: Rows that a term has to be in, and deviations by which its classes (or those of a pair) have to differ.
LEAST_ROWS, SINGLE, PAIR = 5, 3.5, 8.0
#: Of how many of the most frequent terms all pairs are looked at while learning.
PAIR_TERMS = 2048
RANK = 4
MEMO = 300_000
WORD = re.compile(r"[^\W_]+(?:['’][^\W_]+)*")


def bucket(word: str) -> int:
    return zlib.crc32(word.encode("utf-8", "surrogatepass")) & ((1 << HASH_BITS) - 1)


def terms_of(words: list[str]) -> Iterator[int]:
    """Hashed words and stems; the sign after a stem keeps it apart from an equal word."""
    for w in words:
        yield bucket(w)
        if len(w) > STEM:
            yield bucket(w[:STEM] + "-")


def buckets(text: str) -> list[int]:
    """Hashed terms of a text, each once."""
    return sorted(set(terms_of(WORD.findall(text.lower()))))


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -60, 60)))


class Presence:
    """Which rows have which columns: sorted by row, and the same sorted by column."""

    def __init__(self, lists: list[np.ndarray], columns: int):
        self.rows, self.columns = len(lists), columns
        self.col = np.concatenate([*lists, np.zeros(0, np.int64)]).astype(np.int64)
        self.row = np.repeat(np.arange(len(lists)), [len(x) for x in lists])
        self.order = np.argsort(self.col, kind="stable")

    @staticmethod
    def _sums(values: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
        """Sums of the values of each owner; owners ascend."""
        out = np.zeros((n, *values.shape[1:]), values.dtype)
        if len(values):
            starts = np.flatnonzero(np.diff(owner, prepend=-1))
            out[owner[starts]] = np.add.reduceat(values, starts, axis=0)
        return out

    def by_row(self, of_columns: np.ndarray) -> np.ndarray:
        return self._sums(of_columns[self.col], self.row, self.rows)

    def by_column(self, of_rows: np.ndarray) -> np.ndarray:
        return self._sums(of_rows[self.row[self.order]], self.col[self.order], self.columns)


@dataclass
class FactorizationMachine:
    """``terms`` are the buckets of the columns; score = sigmoid(bias + sum of weights + products of all pairs of factors)."""

    terms: np.ndarray
    bias: float
    weights: np.ndarray
    factors: np.ndarray

    def raw(self, x: Presence) -> np.ndarray:
        xv = x.by_row(self.factors)
        return self.bias + x.by_row(self.weights) + 0.5 * ((xv**2).sum(1) - x.by_row((self.factors**2).sum(1)))

    def of_columns(self, columns: list[int]) -> float:
        v = self.factors[columns]
        s = v.sum(0)
        return float(sigmoid(np.array(self.bias + self.weights[columns].sum() + 0.5 * (s @ s - (v**2).sum()))))

    def of_terms(self, terms: list[int]) -> float:
        """Score of a text with these buckets."""
        place = {int(t): k for k, t in enumerate(self.terms)}
        return self.of_columns([place[t] for t in terms if t in place])


def _columns(rows: list[np.ndarray], terms: np.ndarray) -> Presence:
    """Presence of ascending ``terms`` in rows of buckets."""
    lists = []
    for r in rows:
        at = np.minimum(np.searchsorted(terms, r), max(len(terms) - 1, 0)) if len(terms) else np.zeros(0, np.int64)
        lists.append(at[terms[at] == r] if len(terms) else at)
    return Presence(lists, len(terms))


def train(rows: list[np.ndarray], y: np.ndarray, terms: np.ndarray, rank: int = RANK, rounds: int = 300, rate: float = 0.05, penalty: float = 2e-4, seed: int = 7) -> FactorizationMachine:
    """Fits weights and factors of the given columns by steps over all rows, each as wide as its running moments allow."""
    x = _columns(rows, terms)
    share = float(np.clip(y.mean(), 1e-3, 1 - 1e-3))
    rng = np.random.default_rng(seed)
    model = FactorizationMachine(terms, float(np.log(share / (1 - share))), np.zeros(len(terms)), rng.normal(0, 0.05, (len(terms), rank)))
    state = [np.zeros_like(p) for p in (np.zeros(1), model.weights, model.factors) for _ in range(2)]
    for t in range(1, rounds + 1):
        xv = x.by_row(model.factors)
        raw = model.bias + x.by_row(model.weights) + 0.5 * ((xv**2).sum(1) - x.by_row((model.factors**2).sum(1)))
        miss = (sigmoid(raw) - y) / len(y)
        alone = x.by_column(miss)
        grads = (np.array([miss.sum()]), alone + penalty * model.weights, x.by_column(miss[:, None] * xv) - alone[:, None] * model.factors + penalty * model.factors)
        steps = []
        for k, g in enumerate(grads):
            state[2 * k] = 0.9 * state[2 * k] + 0.1 * g
            state[2 * k + 1] = 0.999 * state[2 * k + 1] + 0.001 * g * g
            steps.append(rate * (state[2 * k] / (1 - 0.9**t)) / (np.sqrt(state[2 * k + 1] / (1 - 0.999**t)) + 1e-9))
        model.bias -= float(steps[0][0])
        model.weights = model.weights - steps[1]
        model.factors = model.factors - steps[2]
    return model


def telling_pairs(rows: list[np.ndarray], miss: np.ndarray, terms: np.ndarray, least: float = PAIR, block: int = 512, chunk: int = 2048) -> np.ndarray:
    """Those of ``terms`` that are in a pair whose rows a machine without it gets wrong one way.

    Of each pair the sum of ``miss`` over its rows is compared with the root of the sum of its squares; blocks of
    columns are multiplied in chunks of rows.
    """
    x = _columns(rows, terms)
    found = np.zeros(len(terms), bool)
    starts = np.searchsorted(x.row, np.arange(x.rows + 1))
    for a in range(0, len(terms), block):
        for b in range(a, len(terms), block):
            wide = [min(block, len(terms) - k) for k in (a, b)]
            total, spread = np.zeros(wide, np.float32), np.zeros(wide, np.float32)
            for s in range(0, x.rows, chunk):
                z = min(x.rows, s + chunk)
                row, col = x.row[starts[s] : starts[z]] - s, x.col[starts[s] : starts[z]]
                here = []
                for k, w in zip((a, b), wide):
                    m = np.zeros((z - s, w), np.float32)
                    own = (col >= k) & (col < k + w)
                    m[row[own], col[own] - k] = 1
                    here.append(m)
                e = miss[s:z, None].astype(np.float32)
                total += here[0].T @ (here[1] * e)
                spread += here[0].T @ (here[1] * e**2)
            high = np.abs(total) > least * np.sqrt(spread + 1.0)
            if a == b:
                np.fill_diagonal(high, False)
            found[a : a + wide[0]] |= high.any(1)
            found[b : b + wide[1]] |= high.any(0)
    return terms[found]


def least_rows(n: int) -> int:
    return min(LEAST_ROWS, max(2, n // 50))


def fit(rows: list, labels: np.ndarray, single: np.ndarray | None = None, frequent: np.ndarray | None = None, **options) -> FactorizationMachine:
    """Learns from the rows' buckets.

    ``single`` are the terms that tell the classes apart by themselves, ``frequent`` those of which pairs are looked
    at; both are found from the rows if not given. Without both classes only the bias is left.
    """
    y = np.asarray(labels, np.float64)
    share = float(np.clip(y.mean() if len(y) else 0.0, 1e-3, 1 - 1e-3))
    if not len(y) or y.min() == y.max():
        return FactorizationMachine(np.zeros(0, np.int64), float(np.log(share / (1 - share))), np.zeros(0), np.zeros((0, RANK)))
    rows = [np.asarray(r, np.int64) for r in rows]
    if single is None or frequent is None:
        ids, inverse, tot = np.unique(np.concatenate(rows), return_inverse=True, return_counts=True)
        pos = np.bincount(inverse, weights=y[np.repeat(np.arange(len(rows)), [len(r) for r in rows])], minlength=len(ids))
        apart = np.abs(pos - share * tot) / np.sqrt(share * (1 - share) * (tot + 1.0))
        enough = tot >= least_rows(len(y))
        single = ids[enough & (apart >= SINGLE)]
        order = np.argsort(-tot, kind="stable")
        frequent = ids[order[enough[order]][:PAIR_TERMS]]
    single, frequent = np.unique(single).astype(np.int64), np.unique(frequent).astype(np.int64)
    model = train(rows, y, single, **options)
    pairs = telling_pairs(rows, sigmoid(model.raw(_columns(rows, single))) - y, frequent)
    if np.isin(pairs, single).all():
        return model
    return train(rows, y, np.union1d(single, pairs), **options)


def learn(docs: DataFrame, labels: DataFrame, label: str = "toxic", max_rows: int = MAX_LABELLED, **options) -> FactorizationMachine:
    """Fits the machine on the driver from at most ``max_rows`` labelled rows.

    Terms are counted and chosen on the executors; the driver gets the chosen ones, and of each row those it has.
    """

    def all_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([buckets(t) for t in b.column(1).to_pylist()], pa.list_(pa.int32())), b.column(2)], names=["doc_id", "terms", "label"])

    sample = labelled_sample(docs, labels, label, max_rows)
    kind = dict(sample.dtypes)["doc_id"]
    rows = checkpointed(sample.mapInArrow(all_terms, f"doc_id {kind}, terms array<int>, label int"))
    n, positive = rows.agg(F.count("*"), F.coalesce(F.sum("label"), F.lit(0))).first()
    if not 0 < positive < n:
        return fit([], np.full(min(n, 1), float(positive > 0)))
    share = float(np.clip(positive / n, 1e-3, 1 - 1e-3))
    counts = rows.select(F.explode("terms").alias("term"), "label").groupBy("term").agg(F.count("*").alias("n"), F.sum("label").alias("pos")).where(F.col("n") >= least_rows(n))
    apart = F.abs(F.col("pos") - share * F.col("n")) / F.sqrt(share * (1 - share) * (F.col("n") + 1.0))
    counts = checkpointed(counts.select("term", "n", (apart >= SINGLE).alias("single")))
    single = np.sort(counts.where("single").select("term").toPandas()["term"].to_numpy(np.int64))
    frequent = np.sort(counts.orderBy(F.desc("n"), "term").limit(PAIR_TERMS).select("term").toPandas()["term"].to_numpy(np.int64))
    wanted = np.union1d(single, frequent).astype(np.int32)

    def own_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [np.asarray(t or [], np.int32) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([t[np.isin(t, wanted)].tobytes() for t in got], pa.binary()), b.column(2)], names=["doc_id", "terms", "label"])

    got = rows.mapInArrow(own_terms, f"doc_id {kind}, terms binary, label int").toArrow().sort_by("doc_id")  # the order of tasks must not matter
    return fit([np.frombuffer(t.as_py(), np.int32) for t in got.column("terms")], got.column("label").to_numpy(), single, frequent, **options)


class _Columns(dict):
    """Columns of the terms in a piece between blanks."""

    def __init__(self, terms: np.ndarray):
        super().__init__()
        self.place = {int(t): k for k, t in enumerate(terms)}

    def __missing__(self, piece: str) -> tuple[int, ...]:
        if len(self) > MEMO:
            self.clear()
        got = tuple(self.place[b] for b in terms_of(WORD.findall(piece)) if b in self.place)
        if len(piece) < 64:
            self[piece] = got
        return got


def score(docs: DataFrame, model: FactorizationMachine, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every whole text; null and empty texts get the score of no terms.

    A map over the rows; repeated rows stay repeated and an empty table gives no rows.
    """
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        columns = _Columns(model.terms)
        for b in batches:
            out = []
            for text in b.column(1).to_pylist():
                found = set()
                for hit in filter(None, map(columns.__getitem__, set((text or "").lower().split()))):
                    found.update(hit)
                out.append(model.of_columns(sorted(found)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.float64())], names=["doc_id", "score"])

    rows = docs.select(id_col, text_col).mapInArrow(run, f"doc_id {kind}, score double")
    return rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
