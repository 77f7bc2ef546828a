"""Vectors as arrays of doubles, and word vectors."""

from __future__ import annotations

import functools
import hashlib
import os
import uuid
import zlib
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reportgraph.sources.io import shared_dir, stored


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def euclidean(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y) * (x.cast("double") - y)), F.lit(0.0), lambda s, x: s + x))


@functools.lru_cache(maxsize=100_000)
def word_vector(word: str, dim: int) -> np.ndarray:
    """Sum of random vectors of a word's letter triples: near for words of like spelling, and known for any word."""
    w = f"<{word.lower()}>"
    grams = [w, *(w[i : i + 3] for i in range(len(w) - 2))]
    v = sum(np.random.default_rng(zlib.crc32(g.encode())).standard_normal(dim) for g in grams)
    return v / np.sqrt(len(grams))


def mean_vector(words: list[str], dim: int, table: dict | None = None) -> np.ndarray:
    if not words:
        return np.zeros(dim)
    return np.mean([table[w] if table and w in table else word_vector(w, dim) for w in words], axis=0)


def load_vectors(path: str, dim: int | None = None) -> dict[str, np.ndarray]:
    """Word vectors of a text file, one word and its numbers a line; a first line with the counts alone is left out."""
    out: dict[str, np.ndarray] = {}
    with open(path, encoding="utf-8") as f:
        for line in f:
            word, *numbers = line.rstrip().split(" ")
            if len(numbers) > 1 and (dim is None or len(numbers) == dim):
                out[word] = np.array(numbers, np.float64)
    return out


#: Tokens of a part, about, and places of a step in it, at most.
PART_TOKENS, STEP = 1_000_000, 512
#: Of skip-grams: words on each side, shared words of no context in a step, and the first rate.
WINDOW, NEGATIVES, RATE = 5, 64, 0.025


@dataclass
class WordVectors:
    """Trained vectors ``word, vector`` in the shared folder, and the number of parts that they are averages of."""

    rows: DataFrame
    parts: int

    def getVectors(self) -> DataFrame:
        return self.rows

    def getNumPartitions(self) -> int:
        return self.parts


def start_vectors(words: list[str], dim: int, seed: int) -> np.ndarray:
    """First vectors, of numbers mixed from the word, the place and the seed; the same in every part."""
    own = np.array([zlib.crc32(w.encode()) for w in words], np.uint64)[:, None] << np.uint64(32)
    x = own + np.uint64(seed * 1_000_003) + np.arange(1, dim + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for shift, times in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB), (31, 1)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(times)
    return ((x >> np.uint64(11)).astype(float) / 2**53 - 0.5).astype("<f4") / dim


def _add_to(m: np.ndarray, at: np.ndarray, change: np.ndarray) -> None:
    """Adds rows to the rows ``at``, which may repeat; those of one are added up first, at most to the length of one."""
    order = np.argsort(at, kind="stable")
    first = np.flatnonzero(np.diff(at[order], prepend=-1))
    total = np.add.reduceat(change[order], first, axis=0)
    m[at[order][first]] += total / np.maximum(1, np.linalg.norm(total, axis=1, keepdims=True))


def skip_grams(texts: list[np.ndarray], vectors: np.ndarray, iterations: int, seed: int) -> np.ndarray:
    """Vectors of words (numbers in ``texts``) after steps that bring each near to the words around it and away from words at random, as often as the texts have them to the power of 3/4."""
    texts = [t for t in texts if len(t) > 1]
    if not texts:
        return vectors
    words, of = np.concatenate(texts), np.repeat(np.arange(len(texts)), [len(t) for t in texts])
    rng, u, v = np.random.default_rng(seed), vectors.copy(), np.zeros_like(vectors)
    often = np.bincount(words, minlength=len(u)) ** 0.75
    often = often.cumsum() / often.sum()
    size = max(16, min(STEP, len(words) // 1000))  # a small part takes many steps too
    steps = range(0, len(words), size)
    for done, s in enumerate([s for _ in range(iterations) for s in steps]):
        rate = RATE * max(1e-4, 1 - done / (iterations * len(steps)))
        at = np.arange(s, min(s + size, len(words)))
        mine = u[words[at]]
        reach = rng.integers(1, WINDOW + 1, len(at))
        change, pairs = np.zeros_like(mine), np.zeros(len(at), "<f4")
        near, moved = [], []
        for o in [o for o in range(-WINDOW, WINDOW + 1) if o]:
            i = np.flatnonzero((abs(o) <= reach) & (at + o >= 0) & (at + o < len(words)))
            i = i[of[at[i] + o] == of[at[i]]]
            other = words[at[i] + o]
            pull = (1 - 1 / (1 + np.exp(-(mine[i] * v[other]).sum(1))))[:, None]
            change[i] += pull * v[other]
            near.append(other)
            moved.append(pull * mine[i])
            pairs[i] += 1
        some = np.searchsorted(often, rng.random(NEGATIVES)).clip(max=len(u) - 1)
        # One word at random stands against each pair, so no common direction grows; all places share many, each of which counts in part.
        push = pairs[:, None] / NEGATIVES / (1 + np.exp(-(mine @ v[some].T)))
        change -= push @ v[some]
        _add_to(u, words[at], rate * change)
        _add_to(v, np.concatenate([*near, some]), rate * np.concatenate([*moved, -(push.T @ mine)]))
    return u


def train_word2vec(sentences: DataFrame, tokens_col: str = "tokens", dim: int = 100, iterations: int = 1, min_count: int = 3, seed: int = 7) -> WordVectors:
    """Skip-gram vectors of all words of the corpus that occur ``min_count`` times or more.

    Sentences are dealt to parts, of which there are as many as the session has cores and more if they would have over ``PART_TOKENS`` tokens. A task learns from
    one part, with the vectors of the words in it, and a word's vector is the mean over the parts, weighted by how often they have it. Vocabulary and
    vectors stay on the executors; the driver gets the number of tokens.
    """
    spark = sentences.sparkSession
    rows = sentences.select(F.filter(tokens_col, lambda t: t.isNotNull()).alias("tokens")).where("size(tokens) > 0")
    total = rows.agg(F.sum(F.size("tokens"))).first()[0] or 0
    parts = max(1, spark.sparkContext.defaultParallelism, -(-total // PART_TOKENS))
    # Dealt in turn, since one sentence may be a tenth of all; written, so both readers find a sentence in one part.
    rows = stored(rows.withColumn("part", F.pmod(F.monotonically_increasing_id(), F.lit(parts)).cast("int")))
    counts = stored(rows.select("part", F.explode("tokens").alias("word")).groupBy("part", "word").agg(F.count("*").alias("n")))
    known = counts.groupBy("word").agg(F.sum("n").alias("all")).where(F.col("all") >= min_count).select("word")
    known = counts.join(known, "word")

    def learn(words: pd.DataFrame, texts: pd.DataFrame) -> pd.DataFrame:
        if not len(words):
            return pd.DataFrame({"word": [], "n": [], "vector": []})
        words = words.sort_values("word")
        place = {w: i for i, w in enumerate(words["word"])}
        numbers = sorted((np.array([place[w] for w in t if w in place], np.int64) for t in texts["tokens"]), key=lambda t: t.tobytes())
        order = np.random.default_rng(seed).permutation(len(numbers))  # no order of rows counts
        got = skip_grams([numbers[i] for i in order], start_vectors(list(place), dim, seed), iterations, seed)
        return pd.DataFrame({"word": words["word"], "n": words["n"].astype(float), "vector": list(got)})

    got = known.groupBy("part").cogroup(rows.groupBy("part")).applyInPandas(lambda a, b: learn(a, b), "word string, n double, vector array<float>")
    mean = got.withColumn("v", array_to_vector(F.col("vector").cast("array<double>"))).groupBy("word").agg(Summarizer.mean(F.col("v"), F.col("n")).alias("vector"))
    return WordVectors(stored(mean), parts)


@functools.lru_cache(maxsize=256)
def _opened(path: str) -> tuple[np.ndarray, np.ndarray]:
    if not os.path.exists(f"{path}.keys.npy"):
        return np.zeros(0, np.uint64), np.zeros((0, 0))
    return np.load(f"{path}.keys.npy", mmap_mode="r"), np.load(f"{path}.vectors.npy", mmap_mode="r")


@functools.lru_cache(maxsize=50_000)
def _found(table: VectorFiles, word: str) -> np.ndarray | None:
    key = _key(word)
    keys, rows = _opened(f"{table.folder}/{key % table.files}")
    at = int(np.searchsorted(keys, np.uint64(key)))
    return rows[at] / max(table.size, 1e-9) if at < len(keys) and keys[at] == key else None


def _key(word: str) -> int:
    return int.from_bytes(hashlib.blake2b(word.encode(), digest_size=8).digest(), "little")


@dataclass(frozen=True)
class VectorFiles:
    """Word vectors in files of the shared folder, which readers map into memory and search; so neither driver nor tasks hold all, and what travels with a task is the folder's name."""

    folder: str
    files: int
    words: int
    size: float

    def __len__(self) -> int:
        return self.words

    def __contains__(self, word: str) -> bool:
        return _found(self, word) is not None

    def __getitem__(self, word: str) -> np.ndarray:
        got = _found(self, word)
        if got is None:
            raise KeyError(word)
        return got


def vector_table(model: WordVectors) -> VectorFiles:
    """All words and vectors of a trained model, in files by a hash of the word in lower case; unit length on average. Of words that differ in case the last by letter counts."""
    rows = model.getVectors()
    spark = rows.sparkSession
    folder = f"{shared_dir(spark).rstrip('/').removeprefix('file:')}/vectors-{uuid.uuid4().hex}"
    files = max(1, spark.sparkContext.defaultParallelism, -(-rows.count() // 50_000))

    @F.pandas_udf("int")
    def file_of(words: pd.Series) -> pd.Series:
        return words.map(lambda w: _key(w) % files).astype("int32")

    def write(pdf: pd.DataFrame) -> pd.DataFrame:
        v = np.stack(pdf["vector"]).astype("<f8")
        keys = np.array([_key(w) for w in pdf["word"]], np.uint64)
        order, path = np.argsort(keys), f"{folder}/{pdf['file'].iloc[0]}"
        os.makedirs(folder, exist_ok=True)
        for name, a in (("keys", keys[order]), ("vectors", v[order])):  # a task that runs twice writes the same
            own = f"{path}.{name}.{uuid.uuid4().hex}.npy"
            np.save(own, a)
            os.replace(own, f"{path}.{name}.npy")
        return pd.DataFrame({"words": [len(v)], "size": [float(np.sqrt((v**2).mean(1)).sum())]})

    last = rows.groupBy(F.lower("word").alias("word")).agg(F.max_by(vector_to_array("vector"), F.col("word")).alias("vector"))
    done = last.withColumn("file", file_of("word")).groupBy("file").applyInPandas(write, "words long, size double").collect()
    words = sum(r["words"] for r in done)
    return VectorFiles(folder, files, words, sum(r["size"] for r in done) / max(words, 1))
