"""Routing of reports to teams: feature sets, five classifiers, cross-validation."""

from __future__ import annotations

import functools
import re
from collections.abc import Generator, Iterator
from multiprocessing.pool import ThreadPool

import numpy as np
import pandas as pd
from pyspark.ml import Pipeline
from pyspark.ml.classification import LinearSVC, NaiveBayes, OneVsRestModel, RandomForestClassifier
from pyspark.ml.feature import BucketedRandomProjectionLSH, CountVectorizer, StringIndexer, VectorAssembler
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.util import inheritable_thread_target

from reportgraph.functions.vectors import mean_vector
from reportgraph.sources.io import checkpointed

FEATURE_SETS = ("text", "entities", "entities+title")
MODELS = ("forest", "linear_svm", "rbf_svm", "knn", "naive_bayes")
#: Fixed value: published width of word vectors.
DIM = 100
#: Of the support vector machines: steps at most, and the weight of the squared weights.
SVM_STEPS, SVM_PENALTY = 12, 0.001


def sample(reports: DataFrame, n_teams: int = 10, percent: int = 20) -> DataFrame:
    """Resolved reports of the most frequent teams (ties by letter), of which the share with the smallest id remainder by five stays."""
    done = reports.where("resolved")
    top = done.groupBy("team").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "team").limit(n_teams)
    return done.join(F.broadcast(top.select("team")), "team", "left_semi").where(F.pmod("report_id", F.lit(100 // percent)) == 0)


def entity_kind(mentions: DataFrame, value_types: DataFrame, max_words: int = 3, max_distinct: float = 0.5) -> DataFrame:
    """``entity, words, distinct_share, kind``: 'descriptive' if values of letters are long, or of any sort mostly different; else 'categorical'."""
    values = mentions.groupBy("entity", "value").agg(F.count("*").alias("n"))
    # The middle number of words (the lower one of two) from the counts of each number.
    sizes = values.groupBy("entity", F.size(F.split("value", " +")).alias("words")).agg(F.sum("n").alias("n"), F.count("value").alias("different"))
    own = Window.partitionBy("entity")
    upto, total = F.sum("n").over(own.orderBy("words")), F.sum("n").over(own)
    sizes = sizes.select("entity", "n", "different", F.when(2 * upto >= total, F.col("words")).alias("words"))
    m = sizes.groupBy("entity").agg(F.min("words").alias("words"), (F.sum("different") / F.sum("n")).alias("distinct_share"))
    long = F.col("value_type").isin("Alphabetical", "Other") & (F.col("words") > max_words)
    kind = F.when(long | (F.col("distinct_share") > max_distinct), "descriptive").otherwise("categorical")
    return m.join(F.broadcast(value_types.select("entity", "value_type")), "entity").select("entity", "words", F.round("distinct_share", 6).alias("distinct_share"), kind.alias("kind"))


def raw_features(reports: DataFrame, mentions: DataFrame, kinds: DataFrame, feature_set: str, dim: int = DIM) -> DataFrame:
    """``report_id, team, words, described, entries``: texts of which to take mean word vectors (the report's own, and its
    descriptive values), and one-hot entries 'entity=value'."""
    own = reports.select("report_id", "team", "title", "description")
    if feature_set == "text":
        return own.select("report_id", "team", F.concat_ws(" ", "title", "description").alias("words"), F.lit("").alias("described"), F.array().cast("array<string>").alias("entries"))
    m = mentions.join(F.broadcast(kinds.select("entity", "kind")), "entity").join(own.select("report_id"), "report_id", "left_semi")
    per = m.groupBy("report_id").agg(
        F.array_sort(F.collect_set(F.when(F.col("kind") == "categorical", F.concat_ws("=", "entity", "value")))).alias("entries"),
        F.array_join(F.array_sort(F.collect_set(F.when(F.col("kind") == "descriptive", F.col("value")))), " ").alias("described"),
    )
    rows = own.join(per, "report_id", "left")
    words = F.col("title") if feature_set == "entities+title" else F.lit("")
    return rows.select("report_id", "team", words.alias("words"), F.coalesce("described", F.lit("")).alias("described"), F.coalesce("entries", F.array().cast("array<string>")).alias("entries"))


def features(rows: DataFrame, dim: int = DIM, entries: int = 1024) -> DataFrame:
    """``report_id, team, label, features``: one-hot entries (the most frequent ones), then mean word vectors of both texts.

    The column's metadata name the source of each input: an entity, 'title' or 'descriptive values'.
    """

    @F.pandas_udf("array<double>")
    def vec(t: pd.Series) -> pd.Series:
        return t.map(lambda x: mean_vector(re.findall(r"[^\W\d_]+", x or ""), dim).tolist())

    rows = rows.withColumns({"text_vector": array_to_vector(vec("words")), "described_vector": array_to_vector(vec("described"))})
    hot = CountVectorizer(inputCol="entries", outputCol="hot", vocabSize=entries, minDF=2, binary=True)
    # An entry that every row has keeps the vocabulary from being empty.
    rows = rows.withColumn("entries", F.concat("entries", F.array(F.lit("any="))))
    stages = [hot, VectorAssembler(inputCols=["hot", "text_vector", "described_vector"], outputCol="features"), StringIndexer(inputCol="team", outputCol="label", handleInvalid="keep", stringOrderType="alphabetAsc")]
    model = Pipeline(stages=stages).fit(rows)
    names = [*(e.split("=", 1)[0] for e in model.stages[0].vocabulary), *["title"] * dim, *["descriptive values"] * dim]
    return model.transform(rows).select("report_id", "team", "label", F.col("features").alias("features", metadata={"sources": names}))


def fourier(rows: DataFrame, n: int = 500, gamma: float | None = None, seed: int = 7) -> DataFrame:
    """Random Fourier features, whose inner products approach the Gaussian kernel exp(-gamma d^2).

    Without a ``gamma`` it is one over the mean squared distance of two rows, which is twice the sum of the inputs' variances.
    """
    if gamma is None:
        spread = rows.select(Summarizer.variance(F.col("features")).alias("v")).first()["v"].toArray().sum()
        gamma = 1 / max(2 * float(spread), 1e-9)

    @F.pandas_udf("array<double>")
    def mapped(x: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype=object)
        m = np.stack(x)
        rng = np.random.default_rng(seed)
        w, b = rng.normal(0, np.sqrt(2 * gamma), (m.shape[1], n)), rng.uniform(0, 2 * np.pi, n)
        return pd.Series(list(np.sqrt(2 / n) * np.cos(m @ w + b)))

    return rows.withColumn("features", array_to_vector(mapped(vector_to_array("features"))))


#: Rows of a pack, which is what a task of the neighbour search compares with another one at a time.
PACK = 2048


def _packs(rows: DataFrame, keep: np.ndarray, codes: list[str]) -> DataFrame:
    """``n, ids, labels, x, codes``: rows in packs of arrays as bytes, written once. ``x`` are the inputs of ``keep``, compressed, since most are zero."""
    import pyarrow as pa

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in parts:
            for s in range(0, len(pdf), PACK):
                p = pdf.iloc[s : s + PACK].sort_values("report_id")
                x = np.stack(p["x"])[:, keep].astype("<f4")
                c = np.stack([p[c] for c in codes], 1).astype("<i8") if codes else np.zeros((len(p), 0), "<i8")
                zip_ = lambda v: pa.compress(v.tobytes(), "zstd", asbytes=True)
                yield pd.DataFrame([(len(p), p["report_id"].to_numpy("<i8").tobytes(), p["label"].to_numpy("<f8").tobytes(), zip_(x), c.tobytes())], columns=["n", "ids", "labels", "x", "codes"])

    some = rows.select("report_id", "label", vector_to_array("features", "float32").alias("x"), *codes)
    tasks = max(1, -(-rows.count() // PACK))
    return checkpointed(some.repartition(tasks, "report_id").mapInPandas(run, "n int, ids binary, labels binary, x binary, codes binary"))


def _of_pack(n: int, ids: bytes, labels: bytes, x: bytes, codes: bytes, width: int, tables: int) -> tuple[np.ndarray, ...]:
    import pyarrow as pa

    v = np.frombuffer(pa.decompress(x, n * width * 4, "zstd", asbytes=True), "<f4").reshape(n, width)
    return np.frombuffer(ids, "<i8"), np.frombuffer(labels, "<f8"), v, np.frombuffer(codes, "<i8").reshape(n, tables)


class KNearest:
    """k nearest neighbours by exact distances (ties: the smaller id) among all training rows.

    Rows are packed, and each pair of a pack to predict and a pack to learn from is compared by itself, giving ``k`` rows for each of the
    former; so neither the driver nor a task holds more than two packs. Inputs that have one value in all training rows do not change the order and are left out.
    """

    codes: list[str] = []

    def __init__(self, k: int = 5):
        self.k = k

    def fit(self, rows: DataFrame) -> KNearest:
        spread = rows.select(Summarizer.metrics("min", "max").summary(F.col("features")).alias("s")).select("s.min", "s.max").first()
        lo, hi = (np.asarray(v.toArray()) if v is not None else np.zeros(0) for v in spread)
        self.keep = np.flatnonzero(lo != hi)
        self.packs = _packs(rows, self.keep, self.codes)
        return self

    def neighbours(self, rows: DataFrame) -> DataFrame:
        """``report_id, other, vote, distance, rank``."""
        k, width, tables = self.k, len(self.keep), len(self.codes)
        asked = _packs(rows, self.keep, self.codes)
        names = ["n", "ids", "labels", "x", "codes"]
        pairs = asked.select(*[F.col(c).alias(f"q_{c}") for c in names]).crossJoin(self.packs.select(*[F.col(c).alias(f"t_{c}") for c in names]))

        def compare(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in parts:
                for row in pdf.itertuples(index=False):
                    q_id, _, q, q_code = _of_pack(*row[:5], width, tables)
                    t_id, t_label, t, t_code = _of_pack(*row[5:], width, tables)
                    length = (t**2).sum(1)
                    for s in range(0, len(q_id), 512):
                        d = length[None] - 2 * q[s : s + 512] @ t.T  # the query's own length does not change the order
                        if tables:
                            met = np.zeros(d.shape, bool)
                            for h in range(tables):
                                met |= q_code[s : s + 512, h, None] == t_code[None, :, h]
                            d[~met] = np.inf
                        last = np.partition(d, min(k, len(t_id)) - 1, axis=1)[:, min(k, len(t_id)) - 1]
                        i, j = np.nonzero((d <= last[:, None]) & np.isfinite(d))
                        v = d[i, j]
                        order = np.lexsort((j, v, i))  # ids ascend in a pack
                        i, j, v = i[order], j[order], v[order]
                        at = np.arange(len(i)) - np.searchsorted(i, i)
                        i, j, v = i[at < k], j[at < k], v[at < k]
                        yield pd.DataFrame({"report_id": q_id[s + i], "other": t_id[j], "vote": t_label[j], "distance": v.astype(float)})

        got = pairs.mapInPandas(compare, "report_id long, other long, vote double, distance double")
        return got.withColumn("rank", F.row_number().over(Window.partitionBy("report_id").orderBy("distance", "other"))).where(F.col("rank") <= k)

    def transform(self, rows: DataFrame, usual: float | None = None) -> DataFrame:
        near = self.neighbours(rows)
        votes = near.groupBy("report_id", "vote").agg(F.count("*").alias("n")).groupBy("report_id").agg(F.min(F.struct((-F.col("n")).alias("n"), "vote"))["vote"].alias("vote"))
        return rows.select("report_id", "label").join(votes, "report_id", "left").select("report_id", "label", F.coalesce("vote", F.lit(usual).cast("double")).alias("prediction"))


class HashedNearest(KNearest):
    """k nearest neighbours among those that share a bucket of random projections; a row without such gets the most frequent label.

    A bucket may hold most rows, so its pairs are not made as rows: packs are compared by their arrays of buckets.
    """

    def __init__(self, k: int = 5, width: float = 2.0, tables: int = 4, seed: int = 7):
        super().__init__(k)
        self.codes = [f"code{i}" for i in range(tables)]
        self.hashes = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=width, numHashTables=tables, seed=seed)

    def _hashed(self, rows: DataFrame) -> DataFrame:
        got = self.model.transform(rows.select("report_id", "label", "features"))
        return got.select("report_id", "label", "features", *[vector_to_array(F.get("hashes", F.lit(i)))[0].cast("long").alias(c) for i, c in enumerate(self.codes)])

    def fit(self, rows: DataFrame) -> HashedNearest:
        self.model = self.hashes.fit(rows)
        self.usual = rows.groupBy("label").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "label").first()["label"]
        return super().fit(self._hashed(rows))

    def transform(self, rows: DataFrame) -> DataFrame:
        return super().transform(self._hashed(rows), self.usual)


def one_against_rest(rows: DataFrame, classifier, parallelism: int = 4) -> OneVsRestModel:
    """A binary model for each class, several at a time; each thread has local properties of its own.

    The library's own way shares one copy of them among its threads, so one that ends a query clears the entry that another one is about to read.
    """
    rows = rows.select("label", "features")
    n = int(rows.agg(F.max("label")).first()[0]) + 1

    def one(k: int):
        return classifier.copy({classifier.labelCol: "own"}).fit(rows.withColumn("own", F.when(F.col("label") == float(k), 1.0).otherwise(0.0)))

    tasks = [inheritable_thread_target(rows.sparkSession)(functools.partial(one, k)) for k in range(n)]
    with ThreadPool(min(parallelism, n)) as pool:
        models = pool.map(lambda f: f(), tasks)
    return OneVsRestModel(models=models)


def fit(rows: DataFrame, model: str, seed: int = 7):
    """A fitted classifier with ``transform``."""
    if model == "forest":
        return RandomForestClassifier(numTrees=20, maxDepth=9, seed=seed).fit(rows)
    if model in ("linear_svm", "rbf_svm"):
        return one_against_rest(rows, LinearSVC(maxIter=SVM_STEPS, regParam=SVM_PENALTY))
    if model == "knn":
        return KNearest().fit(rows)
    if model == "knn_hashed":
        return HashedNearest().fit(rows)
    if model == "naive_bayes":
        return NaiveBayes(modelType="gaussian").fit(rows)
    raise ValueError(model)


def minimum(n: int, steps: int, tol: float = 1e-6, memory: int = 10, trials: int = 20) -> Generator[np.ndarray, tuple[float, np.ndarray], np.ndarray]:
    """A minimum over ``n`` numbers by limited-memory quasi-Newton steps from zero: yields a point, is sent its value and gradient, and returns the last one.

    So many of them can be run side by side, with one pass over the rows for the points that all ask for.
    """
    x = np.zeros(n)
    value, grad = yield x
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(steps):
        size = float(np.linalg.norm(grad))
        if size <= max(tol * abs(value), 1e-8):
            break
        way, used = -grad, []
        for s, y in reversed(pairs):
            used.append(s @ way / (s @ y))
            way = way - used[-1] * y
        if pairs:
            s, y = pairs[-1]
            way = way * (s @ y / (y @ y))
        for (s, y), a in zip(pairs, reversed(used)):
            way = way + (a - y @ way / (s @ y)) * s
        slope, best = way @ grad, None
        step, shrink = (1.0, 0.5) if pairs else (0.5 / size, 0.1)
        for _ in range(trials):
            at = x + step * way
            v, g = yield at
            along, low = g @ way, v <= value + 1e-4 * step * slope
            if low and (best is None or v < best[1]):
                best = at, v, g
            if not low or along > -0.9 * slope:
                step *= shrink
            elif along < 0.9 * slope:
                step *= 2.1
            else:
                best = at, v, g
                break
        if best is None:
            if not pairs:
                break
            pairs = []
            continue
        at, v, g = best
        if (at - x) @ (g - grad) > 0:
            pairs = [*pairs, (at - x, g - grad)][-memory:]
        x, value, grad = at, v, g
    return x


class MarginsOfFolds:
    """Linear support vector machines, one for each class against the rest and each fold left out, fitted side by side.

    Each is a minimum of the mean hinge loss of its rows plus the squared weights of the standardised inputs, as the library's ``LinearSVC`` has it. Rows are
    packed once; one pass over the packs gives the losses and gradients of all machines at the points they ask for, so the passes are as
    many as the slowest machine takes, and not as many as all of them. The driver has the weights and, for each task, a sum of gradients.
    """

    def __init__(self, rows: DataFrame, folds: int, steps: int = SVM_STEPS, penalty: float = SVM_PENALTY):
        first = rows.select(F.size(vector_to_array("features")).alias("n")).first()
        self.width, self.folds = (first["n"] if first else 0), folds
        packs = _packs(rows, np.arange(self.width), ["fold"])
        few = 2 * rows.sparkSession.sparkContext.defaultParallelism
        self.packs = packs.coalesce(max(few, packs.rdd.getNumPartitions() // 8))
        self._scales()
        machines = [(k, c) for k in range(folds) for c in range(int(self.classes[k]))]
        self.weights = {m: np.append(np.zeros(self.width), -np.inf) for m in machines}
        self._fit(machines, steps, penalty)

    def _sums(self, of_pack) -> list[np.ndarray]:
        """Sums over all packs of the arrays that ``of_pack(labels, inputs, folds)`` gives."""
        width = self.width

        def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            total = None
            for pdf in parts:
                for row in pdf.itertuples(index=False):
                    _, label, x, fold = _of_pack(*row, width, 1)
                    got = of_pack(label, x.astype(float), fold[:, 0])
                    total = got if total is None else [a + b for a, b in zip(total, got)]
            if total is not None:
                yield pd.DataFrame([(k, list(a.shape), a.astype("<f8").tobytes()) for k, a in enumerate(total)], columns=["k", "shape", "sums"])

        out: dict[int, np.ndarray] = {}
        for r in self.packs.mapInPandas(run, "k int, shape array<int>, sums binary").collect():
            a = np.frombuffer(r["sums"], "<f8").reshape(r["shape"])
            out[r["k"]] = out[r["k"]] + a if r["k"] in out else a
        return [out[k] for k in sorted(out)]

    def _scales(self) -> None:
        """For each fold: rows, mean and deviation of the inputs and number of classes of all rows that are not in it."""
        folds, width = self.folds, self.width

        def of_pack(label: np.ndarray, x: np.ndarray, fold: np.ndarray) -> list[np.ndarray]:
            own = (fold[:, None] == np.arange(folds)).astype(float)
            per = np.zeros((folds, most))
            np.add.at(per, (fold, label.astype(int)), 1.0)
            return [own.sum(0), own.T @ x, own.T @ x**2, per]

        most = int(self.packs.select("labels").mapInPandas(_largest_label, "label double").agg(F.max("label")).first()[0] or 0) + 1
        n, s, q, per = self._sums(of_pack) or [np.zeros(folds), np.zeros((folds, width)), np.zeros((folds, width)), np.zeros((folds, most))]
        self.rows, rest = n, n.sum() - n
        mean = (s.sum(0) - s) / np.maximum(rest, 1)[:, None]
        var = np.maximum((q.sum(0) - q) - rest[:, None] * mean**2, 0) / np.maximum(rest - 1, 1)[:, None]
        # What is left of equal inputs by rounding is no deviation.
        var = np.where(var > 1e-12 * np.maximum((q.sum(0) - q) / np.maximum(rest, 1)[:, None], 1e-300), var, 0)
        self.rest, self.mean, self.scale = rest, mean, np.where(var > 0, 1 / np.sqrt(np.where(var > 0, var, 1)), 0)
        there = per.sum(0) - per > 0
        self.classes = [np.flatnonzero(t).max() + 1 if t.any() else 0 for t in there]

    def _plain(self, point: np.ndarray, fold: int) -> np.ndarray:
        """Weights and intercept for inputs as they are, from those for standardised ones."""
        w = point[:-1] * self.scale[fold]
        return np.append(w, point[-1] - w @ self.mean[fold])

    def _fit(self, machines: list[tuple[int, int]], steps: int, penalty: float) -> None:
        runs = {m: minimum(self.width + 1, steps) for m in machines}
        asked = {m: next(run) for m, run in runs.items()}
        while asked:
            living = list(asked)
            fold, own = np.array([m[0] for m in living]), np.array([float(m[1]) for m in living])
            w = np.stack([self._plain(asked[m], m[0]) for m in living])

            def of_pack(label: np.ndarray, x: np.ndarray, of: np.ndarray, fold=fold, own=own, w=w) -> list[np.ndarray]:
                sign = np.where(label[:, None] == own, 1.0, -1.0)
                gap = np.where(of[:, None] != fold, 1 - sign * (x @ w[:, :-1].T + w[:, -1]), 0)
                up = np.where(gap > 0, -sign, 0.0)
                return [np.maximum(gap, 0).sum(0), up.T @ x, up.sum(0)]

            loss, by_x, by_b = self._sums(of_pack)
            for i, m in enumerate(living):
                k, point = m[0], asked[m]
                grad = np.append((by_x[i] - by_b[i] * self.mean[k]) * self.scale[k], by_b[i]) / self.rest[k]
                grad[:-1] += penalty * point[:-1]
                try:
                    asked[m] = runs[m].send((loss[i] / self.rest[k] + penalty / 2 * float(point[:-1] @ point[:-1]), grad))
                except StopIteration as end:
                    self.weights[m] = self._plain(end.value, k)
                    del asked[m]

    def correct(self) -> np.ndarray:
        """For each fold how many of its rows have the largest margin at their own class; ties to the smaller one."""
        folds, n = self.folds, max([1, *self.classes])
        w = np.zeros((folds, n, self.width + 1))
        w[:, :, -1] = -np.inf
        for (k, c), v in self.weights.items():
            w[k, c] = v

        def of_pack(label: np.ndarray, x: np.ndarray, fold: np.ndarray) -> list[np.ndarray]:
            right = np.zeros(folds)
            for k in range(folds):
                own = fold == k
                right[k] = ((x[own] @ w[k, :, :-1].T + w[k, :, -1]).argmax(1) == label[own]).sum()
            return [right]

        return (self._sums(of_pack) or [np.zeros(folds)])[0]


def _largest_label(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in parts:
        yield pd.DataFrame({"label": [np.frombuffer(b, "<f8").max() for b in pdf["labels"]]})


def cross_validate(rows: DataFrame, model: str, folds: int = 5, only: tuple[int, ...] | None = None) -> DataFrame:
    """``fold, correct, rows``: each fold is predicted from the others; the fold is a hash of the id."""
    rows = fourier(rows) if model == "rbf_svm" else rows
    rows = rows.withColumn("fold", F.pmod(F.xxhash64("report_id"), F.lit(folds)).cast("int"))
    if model in ("linear_svm", "rbf_svm"):
        got = MarginsOfFolds(rows, folds)
        n, right = got.rows.astype(int).tolist(), got.correct().astype(int).tolist()
        return rows.sparkSession.createDataFrame([(k, right[k] if n[k] else None, n[k]) for k in only or range(folds)], "fold int, correct long, rows long")
    rows = rows.persist()
    out = None
    for k in only or range(folds):
        got = fit(rows.where(F.col("fold") != k), model).transform(rows.where(F.col("fold") == k))
        one = got.agg(F.sum((F.col("label") == F.col("prediction")).cast("long")).alias("correct"), F.count("*").alias("rows")).select(F.lit(k).alias("fold"), "correct", "rows")
        out = one if out is None else out.unionByName(one)
    return out


def importances(rows: DataFrame) -> DataFrame:
    """``feature, inputs, importance, rank`` of the forest, summed over the inputs of each source feature."""
    names = rows.schema["features"].metadata["sources"]
    v = fit(rows, "forest").featureImportances
    per: dict[str, list[float]] = {}
    for name, x in zip(names, v.toArray().tolist()):
        per.setdefault(name, []).append(x)
    ranked = sorted(((n, len(xs), sum(xs)) for n, xs in per.items()), key=lambda r: (-r[2], r[0]))
    return rows.sparkSession.createDataFrame([(*r, k) for k, r in enumerate(ranked, 1)], "feature string, inputs int, importance double, rank int")
