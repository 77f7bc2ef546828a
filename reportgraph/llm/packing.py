"""Order-preserving packing of documents into windows, by dynamic programming over cut places.

Documents follow each other in order of id within ranges of ids. A window may begin and end at a
document's end or at any sentence's end within it (and inside a sentence only if no window holds it); of all choices the one with
the least padding plus penalties for documents and sentences cut in two is taken. The best start for each end is the smallest value in a
sliding window of starts, kept in a monotone queue, so the work is linear in the places.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator
from operator import itemgetter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from reportgraph.llm.worker import held, slices
from reportgraph.operators.ranges import range_edges, range_of

WINDOW = 4096
END_ID = 2
#: Penalties, in tokens of padding, for a cut at a sentence's end within a document, and within a sentence.
CUT_PENALTY, SENTENCE_PENALTY = 4, 64
CUT_GAP = 64
MEMO_PIECES, MEMO_WORDS = 350_000, 450_000
SEGMENT_TOKENS = 1 << 18
#: A special token of the vocabulary, put between pieces.
BORDER = "<|endoftext|>"
#: Signs that a word before them is parted from; a run of them is a word of its own.
SIGNS = ".,;:!?%&*#$|)\"-"


class WordIds:
    """Little-endian 32-bit ids of texts, by a tokenizer for which white space is a border and case is nothing.

    Pieces between blanks are looked up; words of letters that are new are given to the library many at
    a time, and its ids are parted at the tokens that end a word. All other pieces go to it as they are.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocab = self.tokenizer.get_vocab(with_added_tokens=True)
        self.last = np.zeros(max(vocab.values()) + 1, bool)
        self.sentence_end = self.last.copy()
        for token, i in vocab.items():
            self.last[i] = token.endswith("</w>")
            self.sentence_end[i] = token.removesuffix("</w>")[-1:] in (".", "!", "?")
        self.pieces: dict[str, bytes] = {"": b""}
        self.words: dict[str, bytes] = {}
        self.signs: dict[str, bytes] = {}
        self.border = self.tokenizer.token_to_id(BORDER)

    def encode(self, text: str) -> bytes:
        # The same ids as from the library's `encode`, which would also follow each token's place in the text.
        return np.asarray(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, "<u4").tobytes()

    def _learn_words(self, words: list[str]) -> None:
        if not words:
            return
        ids = np.frombuffer(self.encode(" ".join(words)), "<u4")
        ends = np.flatnonzero(self.last[ids]) + 1
        if len(ends) != len(words):
            self.words.update((w, self.encode(w)) for w in words)
            return
        raw, at = ids.tobytes(), 0
        for w, e in zip(words, (4 * ends).tolist()):
            self.words[w] = raw[at:e]
            at = e

    def _learn_pieces(self, pieces: list[str]) -> None:
        """Pieces of any signs, parted by a special token that the library finds between them."""
        plain = [p for p in pieces if "<|" not in p and "|>" not in p]
        for p in set(pieces).difference(plain):
            self.pieces[p] = self.encode(p)
        if not plain:
            return
        ids = np.frombuffer(self.encode(BORDER.join(plain)), "<u4")
        ends = np.append(np.flatnonzero(ids == self.border), len(ids))
        raw, at = ids.tobytes(), 0
        for p, e in zip(plain, (4 * ends).tolist()):
            self.pieces[p] = raw[at:e]
            at = e + 4

    def learn(self, pieces: list[str]) -> None:
        """Adds pieces to those known."""
        odd = [p for p in pieces if not p.isascii() and max(p) >= "\u0130"]
        if odd:  # some may have to be composed, or their lower case is more than one letter
            self._learn_pieces(odd)
            pieces = list(set(pieces).difference(odd))
        blob = "\n".join(pieces)
        lows = blob.lower().split("\n") if pieces else []
        cores = [x.rstrip(SIGNS) for x in lows]
        words = self.words
        self._learn_words([w for w in set(cores).difference(words) if w.isalpha()])
        odd, known = [], self.pieces
        for p, low, core in zip(pieces, lows, cores):
            ids = words.get(core)
            if ids is None:
                odd.append(p)
            elif len(low) == len(core):
                known[p] = ids
            else:
                sign = low[len(core) :]
                if sign not in self.signs:
                    self.signs[sign] = self.encode(sign)
                known[p] = ids + self.signs[sign]
        self._learn_pieces(odd)

    def documents(self, texts: list[str]) -> list[bytes]:
        cut = [t.replace("\n", " ").split(" ") for t in texts]
        if len(self.pieces) > MEMO_PIECES or len(self.words) > MEMO_WORDS:
            self.pieces, self.words = {"": b""}, {}
        self.learn(list(set().union(*cut).difference(self.pieces)))
        known = self.pieces
        return [b"".join(itemgetter(*c)(known)) if len(c) > 1 else known[c[0]] for c in cut]


def word_ids(path: str) -> WordIds:
    """This process's ids."""
    return held("packing", path, lambda: WordIds(path))


def by_size(rows: Iterator[tuple], chars: int = 1 << 19) -> Iterator[list[tuple]]:
    """Rows in lists of about so many characters of text (their second column)."""
    out, n = [], 0
    for r in rows:
        out.append(r)
        n += len(r[1])
        if n > chars:
            yield out
            out, n = [], 0
    if out:
        yield out


def cut_places(ids: np.ndarray, ends: np.ndarray, window: int = WINDOW, gap: int = CUT_GAP) -> tuple[np.ndarray, np.ndarray]:
    """Places within a document where it may be cut, and whether each is inside a sentence.

    These are all its sentence ends, and, only in a sentence that no window holds, every ``gap`` tokens.
    """
    at = np.flatnonzero(ends[ids[:-1]]) + 1
    bounds = np.concatenate([[0], at, [len(ids)]])
    wide = np.flatnonzero(np.diff(bounds) > window)
    if not len(wide):
        return at, np.zeros(len(at), bool)
    inner = np.concatenate([np.arange(bounds[k] + gap, bounds[k + 1], gap) for k in wide])
    every = np.concatenate([at, inner])
    order = np.argsort(every, kind="stable")
    return every[order], order >= len(at)


def best_windows(places: list[int], costs: list[int], window: int = WINDOW) -> list[int]:
    """Indexes of the places at which windows end, the last one included.

    ``places`` ascend from 0 by steps of ``window`` at most; ``costs`` are the penalties of cuts there.
    Least total of padding (the last window's is not counted) and penalties; ties go to the later start.
    """
    n = len(places)
    best, came = [0] * n, [0] * n
    queue = deque([0])  # starts of increasing best[i] + places[i]
    keys = [0] * n
    for j in range(1, n):
        p = places[j]
        while p - places[queue[0]] > window:
            queue.popleft()
        i = queue[0]
        came[j] = i
        b = best[j] = keys[i] + window - p + costs[j]
        k = keys[j] = b + p
        while queue and keys[queue[-1]] >= k:
            queue.pop()
        queue.append(j)
    total, last = places[-1], n - 1
    ends = [last]
    # The last window is cut to size by its caller, so it may start anywhere within reach at no padding.
    first = next(i for i in range(n) if total - places[i] <= window)
    last = min(range(first, n - 1), key=lambda i: (best[i], -i)) if first < n - 1 else 0
    while last > 0:
        ends.append(last)
        last = came[last]
    return ends[::-1]


class _Packer:
    """Documents of one range in order; gives back pieces as rows."""

    def __init__(self, base: int, ends: np.ndarray, window: int):
        self.base, self.ends, self.window, self.serial = base, ends, window, 0
        self.docs: list[tuple] = []  # doc_id, ids as bytes, tokens before it already packed
        self.tokens = 0

    def add(self, doc_id, ids: bytes) -> Iterator[tuple]:
        self.docs.append((doc_id, ids, 0))
        self.tokens += len(ids) // 4
        if self.tokens >= SEGMENT_TOKENS:
            yield from self.flush(False)

    def flush(self, final: bool) -> Iterator[tuple]:
        if not self.docs:
            return
        places, costs, at = [0], [0], 0
        for _, ids, done in self.docs:
            n = len(ids) // 4 - done
            cuts, inside = cut_places(np.frombuffer(ids, "<u4")[done:], self.ends, self.window)
            places.extend((cuts + at).tolist())
            costs.extend(np.where(inside, SENTENCE_PENALTY, CUT_PENALTY).tolist())
            at += n
            places.append(at)
            costs.append(0)
        marks = [places[i] for i in best_windows(places, costs, self.window)]
        if not final:
            keep = marks[-2] if len(marks) > 1 else 0
            marks = marks[:-1]
        else:  # the rest in powers of two, so it needs no padding
            start = marks[-2] if len(marks) > 1 else 0
            rest, keep, marks = marks[-1] - start, marks[-1], marks[:-1]
            for k in range(self.window.bit_length() - 1, -1, -1):
                if rest & 1 << k:
                    start += 1 << k
                    marks.append(start)
        yield from self._pieces(marks)
        self._drop(keep)

    def _pieces(self, marks: list[int]) -> Iterator[tuple]:
        begin, k, start = 0, 0, 0  # the current document's begin; the current window and its start
        for doc_id, ids, done in self.docs:
            n, total = len(ids) // 4 - done, len(ids) // 4
            at = 0
            while at < n and k < len(marks):
                upto = min(n, marks[k] - begin)
                if upto > at:
                    part = ids[4 * (done + at) : 4 * (done + upto)]
                    yield doc_id, done + at, upto - at, zlib.crc32(part), total, self.base + self.serial, begin + at - start
                    at = upto
                if begin + at == marks[k]:
                    start = marks[k]
                    k += 1
                    self.serial += 1
            begin += n
            if k == len(marks):
                break

    def _drop(self, upto: int) -> None:
        left, begin = [], 0
        for doc_id, ids, done in self.docs:
            n = len(ids) // 4 - done
            if begin + n > upto:
                left.append((doc_id, ids, done + max(0, upto - begin)))
            begin += n
        self.docs, self.tokens = left, begin - upto


def pack(docs: DataFrame, tokenizer_path: str, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", end_id: int = END_ID) -> DataFrame:
    """Pieces of all documents with their sequences; one shuffle of the texts by ranges of the id.

    A document's ids are the tokenizer's, without special tokens, and ``end_id`` at the end; a null text
    counts as empty, so it is one id long. Null ids come in a range of their own; rows of one id lie in
    order of their texts; an empty table gives no rows. A sequence ends at a place chosen by
    ``best_windows``; a task's ranges follow each other, and what is left at its end goes into sequences whose lengths are powers of
    two, which need no padding. A task holds ``SEGMENT_TOKENS`` tokens and one document at a time.
    """
    kind = dict(docs.dtypes)[id_col]
    edges = range_edges(docs, id_col)
    parts = max(len(edges) + 1, 1)
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    rows = rows.withColumn("__range", range_of(F.col("doc_id"), edges))
    n = min(parts, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    rows = rows.repartition(n, "__range").sortWithinPartitions("__range", "doc_id", "text")
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    own = next(f for f in to_arrow_schema(rows.schema) if f.name == "doc_id")
    schema = pa.schema([own] + [pa.field(c, pa.int64()) for c in names[1:]])
    end = np.asarray([end_id], "<u4").tobytes()

    def batch(got: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*got), schema)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = word_ids(tokenizer_path)
        packer, out = None, []
        for part in by_size(row for b in slices(batches) for row in zip(*(b.column(k).to_pylist() for k in range(3)))):
            for (doc_id, _, r), ids in zip(part, words.documents([x[1] for x in part])):
                if packer is None:
                    packer = _Packer((r + 1) << 40, words.sentence_end, window)
                out.extend(packer.add(doc_id, ids + end))
                if len(out) > 20_000:
                    yield batch(out)
                    out = []
        if packer is not None:
            out.extend(packer.flush(True))
        if out:
            yield batch(out)

    return rows.mapInArrow(run, f"doc_id {kind}, " + ", ".join(f"{c} long" for c in names[1:]))
