"""SimHash near-duplicates with a covering code as anchor points.

A fingerprint is cut into segments. If two fingerprints differ in at most ``threshold`` bits, one of
their segments differs in at most ``threshold // segments`` bits, which has to be 1 or less. A segment's anchors are
the words of a perfect code of radius 1 over its first 15 bits, joined to any values of the others. Each
fingerprint is at home at its segment's anchor and is also sent to every anchor within covering radius plus
1; so two segments one bit apart meet at the home of either. Fingerprints that share an
anchor are compared in full, homes against all. What comes out of an anchor is a forest of links, never all
pairs of a dense group; components over these links are those over all links.
"""

from __future__ import annotations

import math
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reportgraph.llm.worker import slices, turn
from reportgraph.operators.components import connected_components
from reportgraph.operators.hot import join_hot, small_or_not
from reportgraph.sources.io import checkpointed

CODE_BITS = 15
SEED = 42


def _code() -> tuple[np.ndarray, np.ndarray]:
    """For each 15-bit value the code word within one bit; for each syndrome the flips to the words two bits away.

    The syndrome of a value is the exclusive or of the numbers (1 to 15) of its set bits.
    """
    values = np.arange(1 << CODE_BITS)
    syndrome = np.zeros_like(values)
    for k in range(CODE_BITS):
        syndrome ^= np.where(values >> k & 1, k + 1, 0)
    home = values ^ np.where(syndrome > 0, 1 << np.maximum(syndrome - 1, 0), 0)
    flips = np.zeros((16, 7), np.int64)
    for s in range(1, 16):
        flips[s] = [1 << a - 1 | 1 << b - 1 for a in range(1, 16) for b in range(a + 1, 16) if a ^ b == s]
    return home, flips[syndrome]


_HOME, _FLIPS = _code()


def segment_anchors(value: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(position, anchor, is_home)`` of all anchors to which segment values are sent."""
    low, high = value & ((1 << CODE_BITS) - 1), value >> CODE_BITS
    home = _HOME[low]
    n = len(value)
    at = [np.arange(n)]
    anchors = [high << CODE_BITS | home]
    off = np.flatnonzero(home != low)  # a code word's neighbours are three bits away
    at.append(np.repeat(off, 7))
    anchors.append(np.repeat(high[off], 7) << CODE_BITS | (low[off, None] ^ _FLIPS[low[off]]).ravel())
    for k in range(bits - CODE_BITS):
        at.append(np.arange(n))
        anchors.append((high ^ 1 << k) << CODE_BITS | home)
    at_all = np.concatenate(at)
    return at_all, np.concatenate(anchors), np.arange(len(at_all)) < n


def cut(words: np.ndarray, segments: list[tuple[int, int, int]]) -> Iterator[tuple[int, np.ndarray, int]]:
    """``(number, values, bits)`` for segments given as (word, shift, bits)."""
    for k, (word, shift, bits) in enumerate(segments):
        yield k, (words[:, word] >> np.uint64(shift) & np.uint64((1 << bits) - 1)).astype(np.int64), bits


def bit_sums(hashes: np.ndarray, step: int = 1 << 18) -> np.ndarray:
    """How many of the 64-bit hashes (or rows of such) have each bit."""
    width = hashes.reshape(len(hashes), -1).shape[1]
    total = np.zeros(64 * width, np.int64)
    for i in range(0, len(hashes), step):
        total += np.unpackbits(np.ascontiguousarray(hashes[i : i + step]).view(np.uint8).reshape(-1, 8 * width), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return total


def majority(hashes: np.ndarray) -> np.ndarray:
    """Words whose bits are set in over half of the hashes."""
    return np.packbits(bit_sums(hashes) * 2 > len(hashes), bitorder="little").view(np.uint64)


def tokens(text: str | None) -> list[bytes]:
    """Words between blanks and control white space, A-Z in lower case."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def shingle_hashes(words: list[bytes], size: int) -> np.ndarray:
    """XXH64 of the shingles, repeats included; fewer words than a shingle make one."""
    if not words:
        return np.zeros(0, np.uint64)
    h = xxhash.xxh64_intdigest
    if size == 4 and len(words) > 4:
        return np.fromiter((h(b" ".join(s), SEED) for s in zip(words, words[1:], words[2:], words[3:])), np.uint64, len(words) - 3)
    n = max(1, len(words) - size + 1)
    return np.fromiter((h(b" ".join(words[i : i + size]), SEED) for i in range(n)), np.uint64, n)


def fingerprint(text: str | None, size: int = 4) -> int:
    """64-bit SimHash of the word shingles; zero if there is no word."""
    hashes = shingle_hashes(tokens(text), size)
    return int(majority(hashes)[0]) if len(hashes) else 0


def fingerprints(docs: DataFrame, size: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, fp`` (the 64 bits as a signed long) of every row."""
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn("simhash")
        for b in slices(batches):
            fp = np.array([fingerprint(t, size) for t in b.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp)], names=["doc_id", "fp"])

    return docs.select(id_col, text_col).mapInArrow(run, f"doc_id {kind}, fp long")


def _forest(words: np.ndarray, homes: np.ndarray, threshold: int, cells: int = 1 << 22) -> list[tuple[int, int]]:
    """Links that connect the members of one anchor as all links between homes and members would."""
    n, which = len(words), np.flatnonzero(homes)
    if len(which) * n <= cells:
        near = np.bitwise_count(words[which, None, :] ^ words[None, :, :]).sum(-1) <= threshold
        near[np.arange(len(which)), which] = False
        if not near.any():
            return []
        a, b = np.nonzero(near)
        if len(a) <= n:
            return list(zip(which[a].tolist(), b.tolist()))
    # Breadth first, comparing with what has not been reached yet: dense groups are reached in a few steps.
    left, out = np.arange(n), []
    while len(left):
        start, left = left[0], left[1:]
        queue = deque([start])
        while queue and len(left):
            at = queue.popleft()
            close = np.bitwise_count(words[left] ^ words[at]).sum(-1) <= threshold
            for x in left[close].tolist():
                out.append((x, int(at)))
                queue.append(x)
            left = left[~close]
    return out


def _nearest(words: np.ndarray, homes: np.ndarray, threshold: int, cells: int = 1 << 26) -> list[tuple[int, int]]:
    """Candidates among the members of one anchor, which lie in order of their first document.

    All pairs of a home and a member within the threshold, if they are at most four times the members. In
    denser groups each home has its three nearest, its nearest earlier and its earliest one. An anchor of more than
    ``cells`` such pairs is read in windows that overlap by half. What this leaves out is for ``prefix_pairs``.
    """
    n, which = len(words), np.flatnonzero(homes)
    if len(which) * n > cells and n > 2:
        wide = max(2, min(math.isqrt(cells), n - 1))
        out: set[tuple[int, int]] = set()
        for start in range(0, max(1, n - wide // 2), max(1, wide // 2)):
            z = min(n, start + wide)
            out.update((start + i, start + j) for i, j in _nearest(words[start:z], homes[start:z], threshold, wide * wide))
        return list(out)
    far = 1 << 20
    every: list[tuple[int, int]] | None = []
    some: set[tuple[int, int]] = set()
    step = max(1, (1 << 20) // n)
    for k in range(0, len(which), step):
        part = which[k : k + step]
        rows = np.arange(len(part))
        d = np.bitwise_count(words[part, None, :] ^ words[None, :, :]).sum(-1).astype(np.int64)
        d[rows, part] = far
        near = d <= threshold
        if every is not None:
            i, j = np.nonzero(near)
            every.extend(zip(part[i].tolist(), j.tolist()))
            if len(every) > 4 * n:
                every = None
        three = np.argpartition(d, min(3, n - 1), axis=1)[:, :3]
        earlier = np.where(np.arange(n)[None, :] < part[:, None], d, far).argmin(1)
        for c in (*three.T, earlier, near.argmax(1)):
            ok = near[rows, c]
            some.update(zip(part[ok].tolist(), c[ok].tolist()))
    return every if every is not None else list(some)


def _whole_runs(tables: Iterator[list[np.ndarray]]) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
    """Columns sorted by the first of them, cut so that equal values stay together, and where its value changes."""
    kept: list[list[np.ndarray]] = []

    def whole(parts: list[list[np.ndarray]]) -> tuple[list[np.ndarray], np.ndarray]:
        t = [np.concatenate(x) for x in zip(*parts)] if len(parts) > 1 else parts[0]
        return t, np.flatnonzero(np.diff(t[0])) + 1

    for t in tables:
        if not len(t[0]):
            continue
        last = int(np.searchsorted(t[0], t[0][-1]))  # where the last value begins
        if kept and (last or t[0][0] != kept[-1][0][-1]):
            if last:
                kept.append([x[:last] for x in t])
            yield whole(kept)
            kept = [[x[last:] for x in t]]
        elif last:
            yield whole([[x[:last] for x in t]])
            kept = [[x[last:] for x in t]]
        else:
            kept.append(t)  # one value goes on; its parts are joined once, when it ends
    if kept:
        yield whole(kept)


def anchor_links(prints: DataFrame, words: list[str], segments: list[tuple[int, int, int]], threshold: int, nearest: bool = False) -> DataFrame:
    """``(src, dst)`` nodes of linked fingerprints; ``prints`` has a distinct ``node`` and the word columns.

    With ``nearest`` it also has ``place``, by which the members of an anchor are ordered, and links are candidates.

    Replicas are dealt by anchor; a task reads its anchors one after another.
    """
    k = len(words)
    names = ["anchor", "node", "home", *words, "place"]

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for start in range(0, whole.num_rows, 4096):
                b = whole.slice(start, 4096)
                node, place = (b.column(i).to_numpy(zero_copy_only=False) for i in (0, 1 + k))
                fp = np.stack([b.column(1 + i).to_numpy(zero_copy_only=False) for i in range(k)], 1).view(np.uint64)
                for number, values, bits in cut(fp, segments):
                    at, anchor, home = segment_anchors(values, bits)
                    yield pa.RecordBatch.from_arrays([pa.array(anchor | number << 40), pa.array(node[at]), pa.array(home), *[pa.array(fp[at, i].view(np.int64)) for i in range(k)], pa.array(place[at])], names=names)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        link = _nearest if nearest else _forest
        src: list[int] = []
        dst: list[int] = []
        columns = ([b.column(i).to_numpy(zero_copy_only=False) for i in range(3 + k)] for b in batches)
        for t, bounds in _whole_runs(columns):
            node, home, fp = t[1], t[2].astype(bool), np.stack(t[3:], 1).view(np.uint64)
            starts = np.concatenate([[0], bounds, [len(node)]])
            for a, z in zip(starts[:-1].tolist(), starts[1:].tolist()):
                if z - a > 1 and home[a:z].any():
                    for i, j in link(fp[a:z], home[a:z], threshold):
                        src.append(int(node[a + i]))
                        dst.append(int(node[a + j]))
            if len(src) > 20_000:
                yield pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], names=["src", "dst"])
                src, dst = [], []
        yield pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], names=["src", "dst"])

    order = F.col("place") if nearest else F.col("node")
    rows = prints.select("node", *words, order.alias("place")).mapInArrow(spread, "anchor long, node long, home boolean, " + ", ".join(f"{w} long" for w in words) + ", place long")
    n = int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = rows.repartition(n, "anchor").sortWithinPartitions("anchor", "place", "node").drop("place")
    links = rows.mapInArrow(compare, "src long, dst long")
    return links.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).where("src <> dst").distinct()


def simhash_components(docs: DataFrame, size: int = 4, threshold: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, fingerprint, component_id`` of every row; the component is the smallest id that links reach.

    ``threshold`` may be at most 5 (three segments, each with one bit to spare). Null texts have no words; texts
    without words have fingerprint zero and link as any other. Null ids are never the smallest; if a component has no
    other, its id is null. Repeated rows give repeated rows.
    """
    if threshold > 5:
        raise ValueError("three segments with one bit each allow five differing bits")
    prints = checkpointed(fingerprints(docs, size, id_col, text_col))
    distinct = prints.groupBy(F.col("fp").alias("node")).agg(F.min("doc_id").alias("first"), F.count("*").alias("n"))
    links = anchor_links(distinct.select("node", F.col("node").alias("w0")), ["w0"], [(0, 0, 21), (0, 21, 21), (0, 42, 22)], threshold)
    linked = distinct.join(connected_components(links), "node")
    least = checkpointed(linked.groupBy("component").agg(F.min("first").alias("least"), F.count("*").alias("n")))
    linked = join_hot(linked.select("node", "component"), least, "component", ["node"]).select("node", "least")
    ids = checkpointed(distinct.join(linked, "node", "left").select(F.col("node").alias("fp"), F.coalesce("least", "first").alias("component_id"), "n"))
    return join_hot(prints, ids, "fp", ["doc_id"], "inner").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


# --- near-duplicates by similarity of five-word shingles, with SimHash for candidates ---

SHINGLE = 5
SIMILARITY = 0.8
WIDE_WORDS = 3
#: One segment of each word finds most near copies; what it leaves is for ``prefix_pairs``.
WIDE_SEGMENTS = [(word, 0, 21) for word in range(WIDE_WORDS)]
WIDE_THRESHOLD = 40


def wide_print(words: list[bytes]) -> np.ndarray:
    """192-bit SimHash of the distinct words; far less disturbed by a changed word than that of shingles."""
    if not words:
        return np.zeros(WIDE_WORDS, np.uint64)
    own = list(set(words))
    h = xxhash.xxh3_64_intdigest
    hashes = np.array([[h(w, seed) for seed in range(WIDE_WORDS)] for w in own], np.uint64)
    return majority(hashes)


def similarity(a: str, b: str, size: int = SHINGLE) -> float:
    """Jaccard similarity of the sets of word shingles; two texts without words are equal."""
    x, y = (set(shingle_hashes(tokens(t), size).tolist()) for t in (a, b))
    return len(x & y) / len(x | y) if x or y else 1.0


def shingle_keys(words: list[bytes], size: int) -> np.ndarray:
    """Distinct 64-bit keys of the shingles in ascending order, computed from the hashes of the words."""
    if not words:
        return np.zeros(0, np.uint64)
    own = {w: xxhash.xxh3_64_intdigest(w) for w in set(words)}
    h = np.fromiter(map(own.__getitem__, words), np.uint64, len(words))
    n = max(1, len(words) - size + 1)
    key = np.zeros(n, np.uint64)
    for k in range(min(size, len(words))):
        key = (key ^ h[k : k + n]) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    return np.unique(key)


def prefix(keys: np.ndarray, common: np.ndarray, rank: np.ndarray, least: float) -> tuple[np.ndarray, int]:
    """The keys of which two sets with a similarity of ``least`` must share one, and how many of them are ``common``.

    All sets are read in one order: keys that are not ``common`` ascending, then the common ones by ``rank``.
    """
    if not len(keys):
        return keys, 0
    plain = len(keys)
    if len(common):
        at = np.minimum(np.searchsorted(common, keys), len(common) - 1)
        hot = common[at] == keys
        plain -= int(hot.sum())
        keys = np.concatenate([keys[~hot], keys[hot][np.argsort(rank[at[hot]])]])
    size = len(keys) - math.ceil(least * len(keys) - 1e-9) + 1
    return keys[:size], max(0, size - plain)


def common_keys(rows: DataFrame, size: int, share: int = 5, most: int = 1_000_000) -> tuple[np.ndarray, np.ndarray]:
    """Keys found in several texts of a sample, one in ``share``, and their order from rare to common; the ``most`` common ones of them.

    They only shorten the lists of ``prefix_pairs``; with any other set of keys its result is the same.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn("simhash")
        for b in slices(batches):
            for t in b.column(0).to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array(shingle_keys(tokens(t), size).view(np.int64))], names=["key"])

    some = rows.where(F.pmod("row", F.lit(share)) == 0).select("text").mapInArrow(run, "key long")
    top = some.groupBy("key").agg(F.count("*").alias("n")).where("n > 3").orderBy(F.desc("n"), "key").limit(most).toPandas()
    keys = top["key"].to_numpy(np.int64).view(np.uint64)
    order = np.argsort(keys)
    return keys[order], -order


def prefix_pairs(sets: DataFrame, least: float) -> DataFrame:
    """``(src, dst)`` nodes of different groups (``own``) that may have a similarity of ``least``; none that has is left out.

    ``sets`` has a distinct ``node``, ``own``, the number of its keys ``n``, the keys of its ``prefix`` as bytes, and the number
    of those that are ``common``, which are the last.
    The keys that two prefixes share are counted. Up to where the first of two prefixes ends these are all keys that the sets
    share, and after it they share no more than that set has left; so a pair is kept only if both together may be enough. At a
    common key only pairs are seen that may share it first; so as many as both have may be missing from the count.
    """

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for start in range(0, whole.num_rows, 1024):
                b = whole.slice(start, 1024)
                keys = [np.frombuffer(x, np.int64) for x in b.column(3).to_pylist()]
                count = np.array([len(x) for x in keys], np.int64)
                at = np.repeat(np.arange(len(keys)), count)
                left = np.concatenate([int(n) - np.arange(len(x)) for n, x in zip(b.column(2).to_pylist(), keys)])
                node, own, n, late = (b.column(i).to_numpy(zero_copy_only=False)[at] for i in (0, 1, 2, 4))
                before = np.concatenate([np.arange(len(x)) for x in keys])
                last = before >= count[at] - late
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(node), pa.array(own), pa.array(n), pa.array(left.astype(np.int32)), pa.array(late.astype(np.int32)), pa.array(last)], names=["key", "node", "own", "n", "left", "late", "last"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        columns = ([b.column(i).to_numpy(zero_copy_only=False) for i in range(7)] for b in batches)
        out: list[tuple[np.ndarray, ...]] = []
        size = 0

        def batch() -> pa.RecordBatch:
            parts = [np.concatenate([x[i] for x in out] or [np.zeros(0, np.int64)]) for i in range(5)]
            return pa.RecordBatch.from_arrays([pa.array(parts[0]), pa.array(parts[1]), *[pa.array(x.astype(np.int32)) for x in parts[2:]]], names=["src", "dst", "n1", "n2", "unseen"])

        for (_, node, own, n, left, late, last), bounds in _whole_runs(columns):
            starts = np.concatenate([[0], bounds])
            ends = np.append(bounds, len(node))
            mixed = np.flatnonzero(np.minimum.reduceat(own, starts) != np.maximum.reduceat(own, starts))
            for a, z in zip(starts[mixed].tolist(), ends[mixed].tolist()):
                # Members lie by group, so each is compared with the groups after its own only.
                order = a + np.argsort(own[a:z], kind="stable")
                o, m, r = own[order], n[order].astype(np.int64), left[order].astype(np.int64)
                after = np.searchsorted(o, o, side="right")
                k = 0
                while k < z - a:
                    e = int(min(after[k], k + max(1, (1 << 20) // max(1, z - a - after[k]))))  # rows of one group
                    rest = slice(int(after[k]), z - a)
                    # At most as many keys are shared as come before in both and, from here on, as are left in both.
                    most = np.minimum(r[k:e, None], r[rest])
                    if not last[a]:  # of a common key, only pairs that may share none before it
                        most = most + np.minimum((m - r)[k:e, None], (m - r)[rest])
                    i, j = np.nonzero(most * (1 + least) >= least * (m[k:e, None] + m[rest]) - 1e-6)
                    if len(i):
                        x, y = order[k + i], order[int(after[k]) + j]
                        x, y = np.where(node[x] < node[y], x, y), np.where(node[x] < node[y], y, x)
                        out.append((node[x], node[y], n[x], n[y], np.minimum(late[x], late[y])))
                        size += len(i)
                    if size > 100_000:
                        yield batch()
                        out, size = [], 0
                    k = e
        yield batch()

    rows = sets.select("node", "own", "n", "prefix", "common").where("n > 0").mapInArrow(spread, "key long, node long, own long, n int, left int, late int, last boolean")
    parts = int(sets.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    pairs = rows.repartition(parts, "key").sortWithinPartitions("key").mapInArrow(compare, "src long, dst long, n1 int, n2 int, unseen int")
    pairs = pairs.groupBy("src", "dst", "n1", "n2", "unseen").agg(F.count("*").alias("shared"))
    after = lambda n: F.ceil(least * F.col(n) - 1e-9) - 1  # noqa: E731 - keys after a prefix
    enough = least / (1 + least) * (F.col("n1") + F.col("n2")) - 1e-6
    return pairs.where(F.col("shared") + F.col("unseen") + F.greatest(after("n1"), after("n2")) >= enough).select("src", "dst")


def near_duplicate_groups(docs: DataFrame, similarity_least: float = SIMILARITY, size: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc, row, node, kept, kept_row`` of every row: its id, the digest of its text and that of its words, and the id and
    text digest of the first row in its group of near-duplicates (smallest id, nulls last, then smallest text digest).

    Texts of equal words are one node. Two nodes are linked if their shingles' similarity is ``similarity_least``. Near
    fingerprints at each anchor (192 bits, of which three segments with one bit to spare each) give most links and so the
    dense groups; all pairs that these leave in different groups are then looked for by ``prefix_pairs``.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn("simhash")
        for b in slices(batches):
            node, prints, n, keys, late = [], [], [], [], []
            for t in b.column(2).to_pylist():
                w = tokens(t)
                node.append(xxhash.xxh3_64_intdigest(b" ".join(w)))
                prints.append(wide_print(w))
                k = shingle_keys(w, size)
                n.append(len(k))
                first, hot = prefix(k, common, rank, similarity_least)
                keys.append(first.tobytes())
                late.append(hot)
            fp = np.array(prints, np.uint64).reshape(-1, WIDE_WORDS).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(np.array(node, np.uint64).view(np.int64)), *[pa.array(fp[:, i].copy()) for i in range(WIDE_WORDS)], pa.array(n, pa.int32()), pa.array(keys, pa.binary()), pa.array(late, pa.int32())], names=["doc", "row", "node", *words, "n", "prefix", "common"])

    words = [f"w{i}" for i in range(WIDE_WORDS)]
    kind = dict(docs.dtypes)[id_col]
    rows = docs.select(F.col(id_col).alias("doc"), F.col(text_col).alias("text"), F.xxhash64(text_col).alias("row"))
    common, rank = common_keys(rows, size)
    prints = checkpointed(rows.select("doc", "row", "text").mapInArrow(run, f"doc {kind}, row long, node long, " + ", ".join(f"{w} long" for w in words) + ", n int, prefix binary, common int"))
    rank_of = F.struct(F.col("doc").isNull().alias("last"), "doc", "row")
    nodes = prints.groupBy("node").agg(F.min(rank_of).alias("least"), F.count("*").alias("n"), *[F.first(w).alias(w) for w in words]).withColumn("first", F.col("least.doc"))
    number = F.col("first") if kind in ("bigint", "int", "smallint", "tinyint") else F.xxhash64("first")
    placed = nodes.withColumn("place", F.coalesce(number.cast("bigint"), F.lit((1 << 63) - 1)))
    links = checkpointed(anchor_links(placed, words, WIDE_SEGMENTS, WIDE_THRESHOLD, nearest=True))

    @F.pandas_udf("double")
    def likeness(a, b):
        return a.combine(b, lambda x, y: similarity(x or "", y or "", size))

    def verified(pairs: DataFrame) -> DataFrame:
        wanted = pairs.select(F.col("src").alias("node")).union(pairs.select(F.col("dst"))).distinct().join(nodes.select("node", "first", F.col("least.row").alias("first_row")), "node")
        wanted = small_or_not(checkpointed(wanted))
        # The text of a node is that of its first document; neither ids nor their lack say which text that is.
        texts = checkpointed(
            rows.join(wanted, rows["doc"].eqNullSafe(wanted["first"]) & (rows["row"] == wanted["first_row"])).groupBy("node").agg(F.min("text").alias("text"))
        )
        both = pairs.join(texts.select(F.col("node").alias("src"), F.col("text").alias("ta")), "src").join(texts.select(F.col("node").alias("dst"), F.col("text").alias("tb")), "dst")
        return both.where(likeness("ta", "tb") >= similarity_least).select("src", "dst")

    parts = checkpointed(connected_components(verified(links)))
    sets = prints.groupBy("node").agg(F.first("n").alias("n"), F.first("prefix").alias("prefix"), F.first("common").alias("common")).join(parts, "node", "left")
    more = checkpointed(prefix_pairs(sets.withColumn("own", F.coalesce("component", "node")), similarity_least))
    parts = connected_components(verified(more).unionByName(parts.select(F.col("node").alias("src"), F.col("component").alias("dst"))))
    linked = nodes.select("node", "least", "n").join(parts, "node")
    firsts = checkpointed(linked.groupBy("component").agg(F.min("least").alias("kept"), F.count("*").alias("n")))
    linked = join_hot(linked.select("node", "component"), firsts, "component", ["node"]).select("node", "kept")
    groups = nodes.select("node", "least", "n").join(linked, "node", "left").withColumn("kept", F.coalesce("kept", "least"))
    groups = checkpointed(groups.select("node", "n", F.col("kept.doc").alias("kept"), F.col("kept.row").alias("kept_row")))
    return join_hot(prints.select("doc", "row", "node"), groups, "node", ["row", "doc"], "inner").select("doc", "row", "node", "kept", "kept_row")


def one_of_each_group(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` that are the first of their group of near-duplicates, with all columns.

    First is the smallest id, nulls last, then the smallest digest of the text. Of rows of equal id and text one stays.
    """
    groups = near_duplicate_groups(docs, id_col=id_col, text_col=text_col, **options)
    kept = groups.where(F.col("doc").eqNullSafe(F.col("kept")) & (F.col("row") == F.col("kept_row"))).groupBy(F.col("doc").alias("__doc"), F.col("row").alias("__kept")).agg(F.count("*").alias("__times"))
    kept = checkpointed(kept)
    repeated = not kept.where("__times > 1").isEmpty()
    rows = docs.withColumn("__text_digest", F.xxhash64(text_col))
    kept = small_or_not(kept.drop("__times"))
    rows = rows.join(kept, rows[id_col].eqNullSafe(kept["__doc"]) & (rows["__text_digest"] == kept["__kept"]), "left_semi")
    return (rows.dropDuplicates([id_col, "__text_digest"]) if repeated else rows).drop("__text_digest")
