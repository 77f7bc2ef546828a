"""Exact top-k inner products with buckets of vectors of like length.

Candidates are grouped by length. A query's k-th best product so far, divided by its own length and the
largest of a bucket, is the least cosine that a vector of the bucket needs (its local threshold). A
bucket whose threshold is above 1 is skipped; a high threshold prunes by coordinates (a vector near the
query must have a coordinate near the query's on its longest coordinates); a low one prunes by length.
What remains is verified by products, in integers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BUCKET = 1024
QUERY_BLOCK = 8192
PART_ROWS = 1 << 17
LEAST = -(1 << 63)
COORDINATES = 3
#: Cosine from which pruning by coordinates pays.
HIGH = 0.7
EXACT = float(1 << 53)


def matrix(vectors: list, width: int) -> np.ndarray:
    """Rows of doubles; shorter vectors are filled with zeros."""
    if vectors and all(len(v) == width for v in vectors):
        return np.asarray(np.stack(vectors), dtype=np.float64).reshape(len(vectors), width)
    out = np.zeros((len(vectors), width))
    for i, v in enumerate(vectors):
        out[i, : len(v)] = v
    return out


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Inner products of integer-valued rows: in doubles while those are exact, else in Python's integers."""
    if not a.size or not b.size:
        return np.zeros((len(a), len(b)), np.int64)
    if np.abs(a).max() * np.abs(b).max() * a.shape[1] < EXACT:
        return (a @ b.T).astype(np.int64)
    whole = np.vectorize(int, otypes=[object])
    exact = whole(a) @ whole(b).T
    return np.clip(exact, -(1 << 63), (1 << 63) - 1).astype(np.int64)


class BucketSearch:
    """The k best candidates of each query among vectors that come bucket by bucket, longest first."""

    def __init__(self, ids: np.ndarray, queries: np.ndarray, k: int):
        self.ids, self.q, self.k = ids, queries, k
        self.length = np.sqrt((queries**2).sum(1))
        self.best = [np.zeros((0, 2), np.int64)] * len(ids)  # rows of score, id
        self.theta = np.full(len(ids), -np.inf)
        self.skipped = self.verified = 0

    def bucket(self, ids: np.ndarray, vectors: np.ndarray) -> None:
        lengths = np.sqrt((vectors**2).sum(1))
        longest = lengths.max(initial=0.0) * (1 + 1e-12)
        scale = np.maximum(self.length * longest, 1e-300)
        local = np.where(np.isfinite(self.theta), self.theta / scale, -np.inf)
        live = np.flatnonzero(local <= 1 + 1e-9)
        self.skipped += len(self.ids) - len(live)
        high = live[local[live] >= HIGH]
        low = np.setdiff1d(live, high, assume_unique=True)
        for i in high:
            self._take(np.array([i]), *self._by_coordinates(i, local[i], ids, vectors, lengths))
        if len(low):
            # by length: only vectors that reach the least threshold of these queries
            need = np.min(self.theta[low] / np.maximum(self.length[low], 1e-300))
            keep = lengths * (1 + 1e-9) >= need if np.isfinite(need) else np.ones(len(ids), bool)
            self._take(low, ids[keep], vectors[keep])

    def _by_coordinates(self, i: int, cosine: float, ids, vectors, lengths):
        """Vectors whose coordinates lie where a cosine of at least ``cosine`` allows."""
        unit = self.q[i] / max(self.length[i], 1e-300)
        keep = np.ones(len(ids), bool)
        slack = np.sqrt(max(0.0, 1 - min(cosine, 1.0) ** 2)) + 1e-9
        for f in np.argsort(-np.abs(unit))[:COORDINATES]:
            x = vectors[:, f] / np.maximum(lengths, 1e-300)
            spread = slack * np.sqrt(max(0.0, 1 - unit[f] ** 2))
            near = unit[f] * min(cosine, 1.0)  # extremes of a unit vector's coordinate within the cone
            top = 1.0 if abs(unit[f]) >= min(cosine, 1.0) and unit[f] > 0 else near + spread
            low = -1.0 if abs(unit[f]) >= min(cosine, 1.0) and unit[f] < 0 else near - spread
            keep &= (x <= top + 1e-9) & (x >= low - 1e-9)
        return ids[keep], vectors[keep]

    def _take(self, which: np.ndarray, ids: np.ndarray, vectors: np.ndarray) -> None:
        if not len(ids):
            return
        self.verified += len(which) * len(ids)
        scores = products(self.q[which], vectors)
        k = min(self.k, len(ids))
        order = np.argsort(ids, kind="stable")
        at = np.minimum(np.searchsorted(ids[order], self.ids[which]), len(ids) - 1)
        for row in np.flatnonzero(ids[order][at] == self.ids[which]):  # a query's own rows, however many, never take a place
            scores[row, ids == self.ids[which[row]]] = LEAST
        cut = np.partition(scores, len(ids) - k, axis=1)[:, len(ids) - k]
        for row, i in enumerate(which):
            at = np.flatnonzero((scores[row] >= max(cut[row], self.theta[i])) & (ids != self.ids[i]))
            if len(at):
                both = np.concatenate([self.best[i], np.stack([scores[row][at], ids[at]], 1)])
                both = both[np.lexsort((both[:, 1], -both[:, 0]))][: self.k]
                self.best[i] = both
                if len(both) == self.k:
                    self.theta[i] = both[-1, 0]


def in_runs(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[tuple[int, bool, np.ndarray, list]]:
    """``(cell, is_query, ids, vectors)`` of runs of rows of one cell and side, at most ``rows`` each."""
    for b in batches:
        cell, side, ids = (b.column(i).to_numpy(zero_copy_only=False) for i in range(3))
        values = b.column(3)
        bounds = np.flatnonzero((np.diff(cell) != 0) | (np.diff(side) != 0)) + 1
        for a, z in zip([0, *bounds.tolist()], [*bounds.tolist(), len(cell)]):
            for k in range(a, z, rows):
                e = min(z, k + rows)
                vectors = [np.frombuffer(v.as_buffer(), np.float64) for v in values[k:e]]
                yield int(cell[k]), bool(side[k] == 0), ids[k:e], vectors


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, id_col: str = "vec_id", vec_col: str = "embedding", query_block: int = QUERY_BLOCK, bucket: int = BUCKET, part_rows: int = PART_ROWS) -> DataFrame:
    """``query_id, rank, vec_id, score``: for each query the ``k`` best other vectors by integer inner product, ties to the smaller id.

    Components become floor(256 x). Vectors that are null or hold null or non-finite components take
    no part; null ids neither. Vectors of unlike width count as filled with zeros. Repeated ids are
    candidates each for themselves, but never for a query of their id; a query is given once for each id, and of several vectors of
    one id the first in order asks.

    Queries are dealt to blocks of about ``query_block``, candidates to parts of about ``part_rows``; a cell is one block and one part.
    Queries go to the cells of their block, candidates to those of their part, by a shuffle; a task reads the queries of a
    cell, then its candidates, longest first, a bucket at a time. So nothing is collected or broadcast.
    """

    def usable(df: DataFrame) -> DataFrame:
        x = F.col(vec_col)
        ok = F.col(id_col).isNotNull() & x.isNotNull() & F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) != float("inf")))
        return df.where(ok).select(F.col(id_col).cast("bigint").alias("id"), F.transform(x, lambda v: F.floor(v.cast("double") * 256).cast("double")).alias("v"))

    spark = vectors.sparkSession
    cands = usable(vectors)
    asked = usable(queries).groupBy("id").agg(F.min("v").alias("v"))
    blocks = max(1, -(-asked.count() // query_block))
    n = cands.count()
    shuffle = int(spark.conf.get("spark.sql.shuffle.partitions"))
    parts = max(1, -(-n // part_rows), min(shuffle // 2, n // (4 * bucket)))
    # Each part has vectors of all lengths, so every task finds high thresholds early.
    part = F.pmod(F.xxhash64("id", "v"), F.lit(parts))
    block = F.pmod(F.xxhash64("id"), F.lit(blocks))
    length = F.aggregate("v", F.lit(0.0), lambda a, y: a + y * y)
    rows = cands.select(F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(blocks - 1).cast("bigint"))).alias("b"), part.alias("p"), F.lit(1).alias("side"), length.alias("len2"), "id", "v")
    rows = rows.unionByName(asked.select(block.alias("b"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(parts - 1).cast("bigint"))).alias("p"), F.lit(0).alias("side"), F.lit(0.0).alias("len2"), "id", "v"))
    rows = rows.withColumn("cell", F.col("b") * parts + F.col("p"))
    rows = rows.repartition(max(1, min(shuffle, blocks * parts)), "cell").sortWithinPartitions("cell", "side", F.desc("len2"), "id")

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Vectors as bytes of doubles."""
        for b in batches:
            v = b.column(3)
            flat, at = v.values.to_numpy(zero_copy_only=False), v.offsets.to_numpy()
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array([flat[a:z].tobytes() for a, z in zip(at[:-1], at[1:])], pa.binary())], names=["cell", "side", "id", "v"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, search, ids, q = None, None, [], []

        def found() -> pa.RecordBatch:
            out = [(int(i), int(v), int(s)) for i, best in zip(search.ids, search.best) for s, v in best] if search else []
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*out) if out else ([], [], []))], names=["query_id", "vec_id", "score"])

        for cell, is_query, own, values in in_runs(packed(batches), bucket):
            if cell != at:
                yield found()
                at, search, ids, q = cell, None, [], []
            if is_query:
                ids.extend(own.tolist())
                q.extend(values)
                continue
            if search is None:
                search = BucketSearch(np.array(ids, np.int64), matrix(q, max((len(x) for x in q), default=0)), k)
            w = max(search.q.shape[1], max((len(x) for x in values), default=0))
            if w > search.q.shape[1]:
                search.q = np.pad(search.q, ((0, 0), (0, w - search.q.shape[1])))
            if len(ids):
                search.bucket(own, matrix(values, w))
        yield found()

    out = rows.select("cell", "side", "id", "v").mapInArrow(run, "query_id long, vec_id long, score long")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return out.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int"), "vec_id", "score")
