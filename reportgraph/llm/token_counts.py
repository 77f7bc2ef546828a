"""Token counts by a byte-pair tokenizer compiled to a counting transducer.

The tokenizer is two finite-state devices. The outer one cuts a text into words (a pattern without
memory); the inner one reads a word's bytes and keeps, for each start from which a token may still
be under way, its place in the vocabulary's trie, the token before it and how many tokens have come
since. That is finite, so states get numbers when first met, and each transition carries by how much
the count of tokens changes. Which token ends a prefix is unique: the one that the merge rules keep
next to the token before it.

A text is read in chunks. A chunk's state map is kept in symbolic form: between the first and the
last place where every state restarts (a sign followed by white space) the count is a number whatever
comes in; before and after, the text itself stands for the transitions that wait for the neighbour.
Maps compose associatively, and a scan of pairs composes them.
"""

from __future__ import annotations

import json
import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

#: The word pattern of byte-level vocabularies of this kind.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
RESTART = regex.compile(r"(?<=\S)(?=\s)", regex.V1)
CHUNK_CHARS = 1 << 16
MEMO_WORDS = 500_000
MAX_STATES = 400_000
#: White space other than blanks and newlines.
ODD_SPACE = re.compile("[\t\x0b-\r\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins that byte-level vocabularies use: visible Latin-1 signs for themselves, the others from 256 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    out = {chr(b): b for b in plain}
    for k, b in enumerate(b for b in range(256) if chr(b) not in out or out[chr(b)] != b):
        out[chr(256 + k)] = b
    return out


class CountingTransducer:
    """Deterministic transducer over a word's bytes; ``count(word)`` sums the counts on its path."""

    def __init__(self, vocab: dict[bytes, int], ranks: dict[tuple[int, int], tuple[int, int]]):
        self.ranks = ranks
        self.size = {i: len(b) for b, i in vocab.items()}
        self.bytes_of = {i: b for b, i in vocab.items()}
        self.single = [vocab.get(bytes([b])) for b in range(256)]
        self.children: list[dict[int, int]] = [{}]
        self.token: list[int] = [-1]
        for word, i in vocab.items():
            node = 0
            for b in word:
                nxt = self.children[node].get(b)
                if nxt is None:
                    nxt = self.children[node][b] = len(self.children)
                    self.children.append({})
                    self.token.append(-1)
                node = nxt
            self.token[node] = i
        self.spines: dict[int, tuple | None] = {}
        self.reset()

    def reset(self) -> None:
        self.beside: dict[tuple[int, int], bool] = {}
        start = ((0, -1, 0),)
        self.states = [start]
        self.number = {start: 0}
        self.moves: list[dict[int, tuple[int, int]]] = [{}]

    def edges(self, token: int) -> tuple[list[tuple[int, float]], list[tuple[int, float]]] | None:
        """What stands at the token's right and at its left end while the merge rules build it from single bytes.

        Each entry is a piece and the rank of the rule that takes it up (infinite for the token itself).
        None if the rules build something else from the token's bytes.
        """
        if token not in self.spines:
            ids = [self.single[x] for x in self.bytes_of[token]]
            left, right = [], []
            while len(ids) > 1:  # lowest rank first, leftmost of equals
                best = min(((r[0], k) for k in range(len(ids) - 1) if (r := self.ranks.get((ids[k], ids[k + 1])))), default=None)
                if best is None:
                    break
                rank, k = best
                if k == 0:
                    left.append((ids[0], rank))
                if k == len(ids) - 2:
                    right.append((ids[-1], rank))
                ids[k : k + 2] = [self.ranks[ids[k], ids[k + 1]][1]]
            top = (token, math.inf)
            self.spines[token] = ([*right, top], [*left, top]) if ids == [token] else None
        return self.spines[token]

    def can_follow(self, a: int, b: int) -> bool:
        """Whether the rules keep the border between two tokens.

        A rule joins across it if its rank comes before those that take up the two pieces at the border; of
        rules of one rank the left place goes first.
        """
        key = (a, b)
        ok = self.beside.get(key)
        if ok is None:
            x, y = self.edges(a), self.edges(b)
            ok = x is not None and y is not None
            i = j = 0
            while ok:
                (p, until_p), (q, until_q) = x[0][i], y[1][j]
                r = self.ranks.get((p, q))
                if r and r[0] < until_p and r[0] <= until_q:
                    ok = False
                elif until_p == until_q == math.inf:
                    break
                elif until_p <= until_q:
                    i += 1
                else:
                    j += 1
            self.beside[key] = ok
        return ok

    def valid_start(self, b: int) -> bool:
        return self.edges(b) is not None

    def step(self, state: int, byte: int) -> tuple[int, int]:
        items, ended, change = [], -1, 0
        for node, before, since in self.states[state]:
            child = self.children[node].get(byte)
            if child is None:
                continue
            items.append((child, before, since))
            t = self.token[child]
            if ended < 0 and t >= 0 and (self.valid_start(t) if before < 0 else self.can_follow(before, t)):
                ended, change = t, 1 - since
        if ended < 0:
            raise ValueError("the vocabulary lacks single bytes")
        key = tuple((c, p, s + change) for c, p, s in items if self.children[c]) + ((0, ended, 0),)
        to = self.number.get(key)
        if to is None:
            to = self.number[key] = len(self.states)
            self.states.append(key)
            self.moves.append({})
        self.moves[state][byte] = to, change
        return to, change

    def count(self, word: bytes) -> int:
        if len(self.states) > MAX_STATES:
            self.reset()
        state = total = 0
        moves = self.moves
        for b in word:
            move = moves[state].get(b) or self.step(state, b)
            state = move[0]
            total += move[1]
        return total


class _Memo(dict):
    """Counts of pieces seen lately: what stands between two blanks, read with the blank before it unless it begins a line."""

    def __init__(self, machine: CountingTransducer, words):
        super().__init__()
        self.machine, self.words = machine, words
        self.known: dict[str, int] = {}

    def __missing__(self, piece: str) -> int:
        if len(self) > MEMO_WORDS:
            self.clear()
        n = self.segment(piece if piece[0] == "\n" else " " + piece)
        if len(piece) < 64:
            self[piece] = n
        return n

    def segment(self, text: str) -> int:
        total, known = 0, self.known
        for w in self.words(text):
            n = known.get(w)
            if n is None:
                n = self.machine.count(w.encode("utf-8"))
                if len(known) > MEMO_WORDS:
                    known.clear()
                if len(w) < 64:
                    known[w] = n
            total += n
        return total


@dataclass(frozen=True)
class ChunkMap:
    """Text before the first restart, tokens between, text after the last; ``inner`` is None if there is no restart."""

    head: str
    inner: int | None
    tail: str


class Counter:
    """Counts the tokens of texts as the library does for a byte-level vocabulary file."""

    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        model, letters = spec["model"], byte_alphabet()
        plain = {t: bytes(letters[c] for c in t) for t in model["vocab"] if all(c in letters for c in t)}
        special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        vocab = {b: model["vocab"][t] for t, b in plain.items() if t not in special}
        ranks = {}
        for rank, m in enumerate(model["merges"]):
            a, b = m.split(" ") if isinstance(m, str) else m
            ranks[model["vocab"][a], model["vocab"][b]] = rank, model["vocab"][a + b]
        self.special = sorted(special, key=len, reverse=True)
        self.cut = regex.compile("|".join(map(regex.escape, self.special)))
        self.memo = _Memo(CountingTransducer(vocab, ranks), regex.compile(WORD_PATTERN).findall)

    def whole(self, text: str) -> int:
        """Tokens of a text between two restarts (or its ends)."""
        if not any(t in text for t in self.special):
            return self.plain(text)
        parts = self.cut.split(text)
        return len(parts) - 1 + sum(self.plain(p) for p in parts)

    def plain(self, text: str) -> int:
        """Tokens of a text without special strings; single blanks and line starts, where all restarts, cut it into pieces."""
        if text[-1:] in (" ", "\n") and not text[-2:-1].isspace():
            return (self.plain(text[:-1]) if len(text) > 1 else 0) + 1
        if "  " in text or "\n\n" in text or " \n" in text or "\n " in text or text[-1:].isspace() or ODD_SPACE.search(text):
            return sum(map(self.memo.segment, RESTART.split(text)))
        pieces = text.replace("\n", " \n").split(" ")
        first = self.memo.segment(pieces[0]) if pieces[0] else 0
        return first + sum(map(self.memo.__getitem__, pieces[1:]))

    def chunk(self, text: str) -> ChunkMap:
        first = RESTART.search(text)
        if first is None:
            return ChunkMap(text, None, "")
        at, last = first.start(), first.start()
        k = len(text) - 1
        while k > at:  # the last sign that white space follows
            if text[k].isspace() and not text[k - 1].isspace() and RESTART.match(text, k):
                last = k
                break
            k -= 1
        return ChunkMap(text[:at], self.whole(text[at:last]) if last > at else 0, text[last:])

    def compose(self, a: ChunkMap, b: ChunkMap) -> ChunkMap:
        if a.inner is None and b.inner is None:
            both = a.head + b.head
            return self.chunk(both) if RESTART.search(both) else ChunkMap(both, None, "")
        if a.inner is None:
            return self._fold(ChunkMap(a.head + b.head, b.inner, b.tail), front=True)
        if b.inner is None:
            return self._fold(ChunkMap(a.head, a.inner, a.tail + b.head), front=False)
        return ChunkMap(a.head, a.inner + self.whole(a.tail + b.head) + b.inner, b.tail)

    def _fold(self, m: ChunkMap, front: bool) -> ChunkMap:
        """A join may make a restart of its own (a sign at the end of one chunk, white space first in the next)."""
        inside = self.chunk(m.head if front else m.tail)
        if front and inside.inner is not None:
            return ChunkMap(inside.head, inside.inner + self.whole(inside.tail) + m.inner, m.tail)
        if not front and RESTART.search(m.tail, 1):
            tail = self.chunk(" " + m.tail[1:]) if m.tail[:1].isspace() else inside
            if tail.inner is not None:
                cut = len(m.tail) - len(tail.tail)
                return ChunkMap(m.head, m.inner + self.whole(m.tail[:cut]), m.tail[cut:])
        return m

    def scan(self, maps: list[ChunkMap]) -> ChunkMap:
        """Composition of all maps, by pairs."""
        while len(maps) > 1:
            maps = [self.compose(*maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
        return maps[0]

    def count(self, text: str, chunk_chars: int = CHUNK_CHARS) -> int:
        if len(text) <= chunk_chars:
            return self.whole(text)
        m = self.scan([self.chunk(text[i : i + chunk_chars]) for i in range(0, len(text), chunk_chars)])
        return self.whole(m.head) + (m.inner or 0) + self.whole(m.tail)


_READY: dict[str, Counter] = {}


def counter(path: str) -> Counter:
    """The compiled tokenizer of this process."""
    if path not in _READY:
        _READY[path] = Counter(path)
    return _READY[path]


def token_counts(docs: DataFrame, tokenizer_path: str, limit: int = 512, id_col: str = "doc_id", text_col: str = "text", chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` of every row; null texts count as empty, with no tokens.

    A map over the rows: no shuffle. Repeated rows stay repeated, an empty table gives no rows.
    """
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(tokenizer_path)
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            n = [c.count(t, chunk_chars) for t in texts]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([len(t.encode("utf-8")) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    return docs.select(id_col, text_col).mapInArrow(run, f"doc_id {kind}, n_bytes long, n_tokens long, over_limit boolean")
