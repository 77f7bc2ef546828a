"""The training-data operations against brute force, on small fixtures with nulls, ties, repeats and long texts."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from reportgraph.llm import fingerprints, mixing, packing, quality, queries, simhash, substring_dedup, token_counts, topk, toxicity, training, warc

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lamda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, __id string, node long"


def prose(rng, n):
    return " ".join(rng.choice(WORDS) + (rng.choice(WORDS) if rng.random() < 0.7 else "") + ("." if rng.random() < 0.15 else "") for _ in range(n))


def fixture_rows():
    rng = random.Random(11)
    rows = [(i, prose(rng, rng.randint(1, 120)), "en", rng.choice(["a", "b", None, "é"])) for i in range(60)]
    rows += [(100 + i, rows[3][1], "en", "a") for i in range(5)]  # exact copies
    words = rows[7][1].split()
    for i in range(3):  # near copies
        w = list(words)
        w[(5 * i + 1) % len(w)] = "changed"
        rows.append((120 + i, " ".join(w), "en", "b"))
    rows += [(200, None, None, None), (201, "", "en", "b"), (202, " \n\t ", "en", "b"), (None, "no id", "en", "a"), (204, "日本 語 ß İ 😀\nzwei\n\n", None, "é"), (205, "x" * 5000, "en", "a"), (206, prose(rng, 6000), "en", "b")]
    rows += [rows[0]]  # a repeated row
    return [(i, t, la, s, len(t or ""), "clash", 1) for i, t, la, s in rows]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(fixture_rows(), SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def key(i):
    return (i is None, -(i or 0))


def test_fingerprints_by_hand(docs, none):
    got = fingerprints.document_fingerprints(docs).collect()
    rows = [(r[0], r[1] or "") for r in fixture_rows()]
    order = sorted(rows, key=lambda r: (key(r[0]), r[1]))
    want = Counter()
    for k, (i, t) in enumerate(order):
        head = order[(k + 1) % len(order)][1]
        cut = len(t) // 3
        want[i, len(t), hashlib.sha256((t[: len(t) - cut] + head[:cut]).encode()).hexdigest()] += 1
    assert Counter((r["doc_id"], r["n_chars"], r["edited_sha256"]) for r in got) == want
    prints = {}
    for r in got:
        assert 0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1
        prints.setdefault(r["doc_id"], r["fingerprint"])
    assert len({prints[i] for i in (3, 100, 101)}) == 1 and prints[200] == prints[201] != prints[202]
    assert fingerprints.document_fingerprints(none).count() == 0


def print_by_hand(text):
    """The words of a fingerprint, counted one phrase at a time."""
    def signed(x):
        return x - (1 << 64) if x >> 63 else x

    def h(x, *more):
        seed = 42
        out = xxhash.xxh64_intdigest(x.encode(), seed)
        for k in more:
            out = xxhash.xxh64_intdigest(k.to_bytes(4, "little"), out)
        return signed(out)

    words = [0] * (fingerprints.EXACT_WORDS + fingerprints.LANE_WORDS)
    for p in text.split("\n"):
        for k in range(fingerprints.EXACT_WORDS):
            words[k] = (words[k] + h(p, k)) % (1 << 62)
        found = []
        if len(p) >= 64:
            for x in filter(None, re.split(fingerprints.PHRASE_END, p)):
                found += [(y, len(y)) for y in (re.findall(fingerprints.PIECE, x) if len(x) > 32 else [x])]
        if 1 <= len(p) < 96:
            found += [(p[i : i + 3], 1) for i in range(max(len(p) - 2, 1))]
        for x, n in found:
            v = h(x)
            word = (v & 3) + 4 * ((v >> 8) % 10)
            words[4 + word] = (words[4 + word] + (n << 31 * (v >> 2 & 1))) % (1 << 62)
    return words


def likeness_by_hand(a, b):
    if a == b:
        return 1.0
    x, y = ([w >> 31 * i & (1 << 31) - 1 for w in p[4:] for i in (0, 1)] for p in (a, b))
    if min(np.var(x), np.var(y)) < 1e-9:
        return 0.0
    return max(0.0, float(np.corrcoef(x, y)[0, 1]))


def test_fingerprints_and_likeness_by_brute_force(spark, docs):
    rng = random.Random(6)
    rows = sorted({(i, t or "") for i, t, *_ in fixture_rows() if i is not None}, reverse=True)
    han = "".join(chr(rng.randint(0x4E00, 0x9FFF)) for _ in range(1500))
    rows = [(909, "three tiny words"), (908, "hello worldly ab"), (907, "ab"), (906, han), (905, "one line again and again\n" * 20_000), *rows]
    df = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, print int")
    got = {r["doc_id"]: r for r in fingerprints.document_fingerprints(df).collect()}
    for k, (i, t) in enumerate(rows):
        nxt = rows[(k + 1) % len(rows)][1]
        cut = len(t) // 3
        prints = [print_by_hand(x) for x in (t, t[: len(t) - cut] + nxt[:cut], nxt)]
        r = got[i]
        assert r["fingerprint"] == "".join(f"{w:016X}" for w in prints[0]) and r["edited_fingerprint"] == "".join(f"{w:016X}" for w in prints[1])
        assert r["near_edited"] == pytest.approx(likeness_by_hand(prints[0], prints[1]), abs=1e-9)
        assert r["near_next"] == pytest.approx(likeness_by_hand(prints[0], prints[2]), abs=1e-9)
    assert all(got[i]["near_edited"] > 0.4 for i in (905, 906, 908, 909)) and got[905]["near_next"] < 0.2
    names = df.select(F.concat(F.lit("n"), F.lpad(F.col("doc_id").cast("string"), 5, "0")).alias("doc_id"), "text")
    assert {(r["doc_id"], r["edited_sha256"]) for r in fingerprints.document_fingerprints(names).collect()} == {(f"n{i:05d}", r["edited_sha256"]) for i, r in got.items()}


def test_fingerprint_is_homomorphic(spark):
    df = spark.createDataFrame([("b\na\nb", "a\nb", "b", "b\nb\na", "a\nb\nc")], "whole string, x string, y string, mixed string, other string")
    v = {c: fingerprints.vector(c) for c in df.columns}
    r = df.select(*[F.col(c) for c in df.columns], *[v[c].alias(f"v_{c}") for c in df.columns])
    r = r.select(fingerprints.combine(F.col("v_x"), F.col("v_y")).alias("sum"), fingerprints.delete(F.col("v_whole"), F.col("v_y")).alias("rest"), "v_whole", "v_x", "v_mixed", "v_other").first()
    assert r["sum"] == r["v_whole"] == r["v_mixed"] and r["rest"] == r["v_x"] and r["v_other"] != r["v_whole"]


def test_mixing(docs, none):
    rows = mixing.mix(docs, block_tokens=8).collect()
    again = mixing.mix(docs.repartition(5), block_tokens=8).collect()
    assert Counter((r["doc_id"], r["taken"]) for r in rows) == Counter((r["doc_id"], r["taken"]) for r in again)
    sizes, taken, target = Counter(), Counter(), {}
    for r in rows:
        assert 0 <= r["taken"] <= 3 * r["size"]
        assert all(0 <= s["start"] < s["end"] <= r["size"] for s in r["spans"])
        sizes[r["source"]] += r["size"]
        taken[r["source"]] += r["taken"]
        target[r["source"]] = r["target"]
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    want = mixing.capped_targets([sizes[s] for s in order], [1, 2, 3, 1][: len(order)], sum(sizes.values()))
    for s, t in zip(order, want):
        assert target[s] == pytest.approx(t) and taken[s] == round(t)
    assert mixing.mix(none).count() == 0


def test_apportionment_by_quotients():
    rng = random.Random(2)
    for _ in range(30):
        w, n = [rng.randint(0, 50) for _ in range(rng.randint(1, 6))], rng.randint(0, 40)
        seats = [0] * len(w)
        if sum(w):
            for _ in range(n):
                seats[max(range(len(w)), key=lambda i: (w[i] / (2 * seats[i] + 1), -i))] += 1
        assert mixing.sainte_lague(w, n) == seats
    assert mixing.capped_targets([10, 1000, 10], [3, 1, 1], 1020, 3) == [30, 960.0, 30]


def test_mixing_of_small_sources_and_repeated_rows(spark):
    rng = random.Random(5)
    rows = [(1, prose(rng, 10), "a"), (2, None, "a"), *[(10 + i, prose(rng, 500), "bc"[i % 2]) for i in range(20)], (10, prose(rng, 7), "b"), (None, "no id", "c"), (3, "one", None)]
    rows += rows[4:6]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mix(df).collect()
    taken, target = Counter(), {}
    for r in got:
        taken[r["source"]] += r["taken"]
        target[r["source"]] = r["target"]
        assert r["taken"] <= 3 * r["size"]
    assert len(got) == len(rows) and target["a"] == taken["a"] == 30 and taken == {s: round(t) for s, t in target.items()}
    extra = df.withColumns({"h": F.lit(1), "shard": F.lit("x"), "blocks": F.lit(2.0), "d": F.lit(0), "taken": F.lit("t")})
    assert sum(len(simhash.tokens(r["text"])) for r in mixing.mixed_documents(extra).collect()) == sum(taken.values())
    assert mixing.mixed_documents(extra).columns == extra.columns


def test_shard_words_add_up():
    rng = random.Random(3)
    for _ in range(200):
        sizes = [rng.randint(0, 400) for _ in range(rng.randint(1, 6))]
        words = rng.randint(0, sum(sizes))
        got = mixing.shard_words(sizes, words, 64)
        assert sum(got) == words and all(0 <= g <= n for g, n in zip(got, sizes))


def test_mixed_documents_follow_the_mix(docs):
    rows = {r["doc_id"]: r["taken"] for r in mixing.mix(docs, block_tokens=8).groupBy("doc_id").agg(F.sum("taken").alias("taken")).collect()}
    got = mixing.mixed_documents(docs, block_tokens=8).collect()
    assert {r["doc_id"]: len(simhash.tokens(r["text"])) for r in got} == {k: v for k, v in rows.items() if v}
    assert got[0].asDict().keys() == dict.fromkeys(docs.columns).keys()


def test_warc_round_trip(spark, tmp_path):
    html = ["<p>a</p>", "", None, "x\r\n\r\nWARC/1.1\r\n\r\ny", "<p>a</p>", "é" * 3000, "<p>a</p>", "only"]
    pages = spark.createDataFrame([(i if i != 7 else None, ["http://B.example/x?q=1", "http://a.example/", None, "not a url"][i % 4], h, "p") for i, h in enumerate(html)], "page_id long, url string, html string, value string")
    got = warc.archive_pages(pages, str(tmp_path / "w")).collect()
    assert len(got) == 8
    kept = {}
    for i, h in enumerate(html):
        if i != 7:
            kept[h or ""] = i
    for r in got:
        h = html[r["page_id"]] or "" if r["page_id"] is not None else "only"
        import base64

        assert r["payload_bytes"] == len(h.encode()) and r["payload_digest"] == base64.b32encode(hashlib.sha1(h.encode()).digest()).decode()
        last = kept.get(h, r["page_id"])
        assert (r["record_type"], r["refers_to"]) == (("response", None) if last == r["page_id"] else ("revisit", last))
    ordered = sorted(got, key=lambda r: (r["range"], r["place"]))
    keys = [(r["urlkey"], r["ts"], r["page_id"] or -1) for r in ordered]
    assert keys == sorted(keys)
    for r in got:  # each record by its own offset, without the rest of its file
        headers, block = warc.read_record(str(tmp_path / "w" / r["run"]), r["offset"], r["length"])
        assert headers["warc-type"] == r["record_type"] and headers["warc-payload-digest"] == f"sha1:{r['payload_digest']}"
        if r["record_type"] == "response":
            assert block.partition(b"\r\n\r\n")[2] == (html[r["page_id"]] or "" if r["page_id"] is not None else "only").encode()
    assert warc.archive_pages(pages.limit(0), str(tmp_path / "none")).count() == 0


def test_captures_count_over_ranges(spark, tmp_path):
    rows = [(i, "http://hot.example/" if i % 3 else f"http://b{i % 5}.example/", "same" * 2000 if i % 2 else f"<p>{i}</p>") for i in range(2600)] + [(5, "http://hot.example/", "again"), (5, "http://hot.example/", "again"), (2600, None, "x" * 3_000_000)]
    pages = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, digest string").repartition(5)
    got = warc.archive_pages(pages, str(tmp_path / "w"), range_rows=10, file_records=7).collect()
    assert len(got) == len(rows) and len({r["run"] for r in got}) > 300 and len({r["range"] for r in got}) > 100
    histories = {}
    for r in sorted(got, key=lambda r: (r["range"], r["place"])):
        histories.setdefault(r["urlkey"], []).append((r["capture"], r["ts"], r["page_id"]))
    assert len(histories) == 7
    for h in histories.values():
        assert [c for c, _, _ in h] == list(range(1, len(h) + 1)) and [x[1:] for x in h] == sorted(x[1:] for x in h)
    same = [r for r in got if r["payload_bytes"] == 8000]
    assert {r["refers_to"] for r in same if r["record_type"] == "revisit"} == {2599} == {r["page_id"] for r in same if r["record_type"] == "response"}
    again = [r for r in got if r["payload_bytes"] == 5]
    assert [r["record_type"] for r in again] == ["response"] * 2


def test_sql_of_the_operations(spark):
    from harness import compare

    sql = queries.oracle_sql()
    for name, query in queries.queries().items():
        if name in sql:
            compare(query(spark, "/root/testdata/sf0.01"), sql[name], "/root/testdata/sf0.01")


def test_loser_tree():
    rng = random.Random(1)
    for k in (0, 1, 2, 5, 9):
        runs = [sorted(rng.random() for _ in range(rng.randint(0, 12))) for _ in range(k)]
        assert list(warc.LoserTree(runs, lambda r: r)) == sorted(x for r in runs for x in r)


def test_passages(spark, none):
    rng = random.Random(4)
    passage = ". ".join(prose(rng, 12).replace(".", "") for _ in range(6)) + "."
    own = [prose(rng, 60) + "." for _ in range(6)]
    rows = [(1, own[0] + " " + passage + " " + own[1], "e"), (2, own[2] + "\n" + passage.upper() + "\n" + own[3], "e"), (3, own[4], "e"), (4, passage, "e"), (5, None, "e"), (6, "", "e"), (3, own[4], "e"), (None, own[5], "e")]
    df = spark.createDataFrame(rows, "doc_id long, text string, again string")
    got = sorted(((r["doc_id"], r["text"], r["removed_spans"]) for r in substring_dedup.dedup_passages(df).collect()), key=lambda r: (r[0] is None, r[0] or 0))
    text = {i: t for i, t, _ in got}
    assert len(got) == 8 and text[1] == rows[0][1] and text[3] == own[4] and text[5] is None and text[6] == "" and text[None] == own[5]
    assert own[2] in text[2] and own[3] in text[2] and passage.upper() not in text[2] and text[4].strip() == ""
    spans = next(s for i, _, s in got if i == 2)
    assert all(rows[1][1][s["start"] : s["end"]] not in text[2] for s in spans)
    assert substring_dedup.dedup_passages(none).count() == 0


def test_units_cover_lines():
    text = "One two. Three!  Four\nfive six\n\n7.5 is no end"
    assert [text[a:b].strip() for a, b, _, _ in substring_dedup.units(text)] == ["One two.", "Three!", "Four", "five six", "7.5 is no end"]
    rng = random.Random(5)
    words = [f"w{rng.randrange(900)}" for _ in range(400)]
    whole, tail = (substring_dedup.units(" ".join(w) + ".") for w in (words, words[200:]))
    assert all(n <= substring_dedup.LONG_SENTENCE for _, _, n, _ in whole) and sum(n for _, _, n, _ in whole) == 400
    assert [u[3] for u in whole][-10:] == [u[3] for u in tail][-10:]  # cuts do not hang on where a sentence begins


def dedup_by_hand(rows, min_words):
    """Spans removed from each (id, text), reading documents in order and units one by one."""
    def order(r):
        return (r[0] is None, r[0] or 0, row_digest(r))

    def row_digest(r):
        h = 42 if r[0] is None else xxhash.xxh64_intdigest(r[0].to_bytes(8, "little", signed=True), 42)
        h = xxhash.xxh64_intdigest(r[1].encode(), h)
        return h - (1 << 64) if h >> 63 else h

    seen, out = set(), {}
    for r in sorted(set(rows), key=order):
        spans, run = [], []
        for u in [*substring_dedup.units(r[1]), None]:
            if u is not None and u[3] in seen:
                run.append(u)
                continue
            if sum(x[2] for x in run) >= min_words:
                spans.append((run[0][0], run[-1][1]))
            run = []
            if u is not None:
                seen.add(u[3])
        out[r] = spans
    return out


def test_passages_by_brute_force(spark, docs):
    rng = random.Random(14)
    passages = [". ".join(prose(rng, rng.randint(3, 30)).replace(".", "") for _ in range(5)) + "." for _ in range(4)]
    rows = [(r[0], r[1]) for r in fixture_rows()]
    for i in range(60):
        parts = [prose(rng, rng.randint(1, 40)), *rng.sample(passages, rng.randint(0, 2)), prose(rng, 30), "Again the same line of words for all. " * rng.randint(0, 9)]
        rng.shuffle(parts)
        rows.append((300 + i // 2, rng.choice([" ", "\n"]).join(parts)))
    rows += [(500, "very " * 60_000), (501, "very " * 50_000 + "long."), rows[-1], (None, passages[0]), (None, passages[0])]
    df = spark.createDataFrame([(i, t, "x", 7) for i, t in rows], "doc_id long, text string, row string, spans int").repartition(5)
    want = dedup_by_hand([(i, t or "") for i, t in rows], substring_dedup.MIN_WORDS)
    got = substring_dedup.dedup_passages(df)
    assert got.columns == [*df.columns, "removed_spans"]
    expected = Counter()
    for i, t in rows:
        spans = want[i, t or ""]
        kept, at = "", 0
        for a, b in spans:
            kept, at = kept + (t or "")[at:a], b
        expected[i, None if t is None else kept + t[at:], tuple(spans)] += 1
    assert Counter((r["doc_id"], r["text"], tuple((s["start"], s["end"]) for s in r["removed_spans"])) for r in got.collect()) == expected
    assert sum(map(bool, want.values())) > 30
    names = df.withColumn("doc_id", F.concat(F.lit("n"), F.col("doc_id").cast("string")))
    assert substring_dedup.dedup_passages(names).where("size(removed_spans) > 0").count() > 30


def odd_texts():
    rng = random.Random(7)
    bits = ["a", "The", "  ", "\n", " ", "\t", "'s", "'LL", "<|endoftext|>", "é", "É", "日本", "1", "23", "!!", "😀", "x" * 40, " ", "\x1c", "́", "ing", "İ", "ß", ".", "word."]
    return ["".join(rng.choice(bits) for _ in range(rng.randint(0, 30))) for _ in range(400)]


def test_token_counts_as_the_library(spark, docs, none):
    from tokenizers import Tokenizer

    path = queries.tokenizer("byte_bpe_50k.json")
    t, c = Tokenizer.from_file(path), token_counts.Counter(path)
    for s in odd_texts():
        want = len(t.encode(s, add_special_tokens=False).ids)
        assert {c.count(s, n) for n in (1, 2, 3, 7, 10**6)} == {want}, repr(s)
    for r in token_counts.token_counts(docs, path).join(docs.select("doc_id", "text").distinct(), "doc_id").collect():
        text = r["text"] or ""
        n = len(t.encode(text, add_special_tokens=False).ids)
        assert (r["n_bytes"], r["n_tokens"], r["over_limit"]) == (len(text.encode()), n, n > 512)
    assert token_counts.token_counts(docs, path).count() == docs.count() and token_counts.token_counts(none, path).count() == 0


def test_packing_is_complete(spark, docs, none):
    from tokenizers import Tokenizer

    path = queries.tokenizer("word_bpe_49k.json")
    t, w = Tokenizer.from_file(path), packing.WordIds(path)
    texts = odd_texts()
    for s, got in zip(texts, w.documents(texts)):
        assert np.frombuffer(got, "<u4").tolist() == t.encode(s, add_special_tokens=False).ids, repr(s)
    named = docs.where("doc_id is not null").dropDuplicates(["doc_id"])
    ids = {r["doc_id"]: [*t.encode(r["text"] or "", add_special_tokens=False).ids, 2] for r in named.collect()}
    pieces, seqs = {}, {}
    for r in packing.pack(named, path).collect():
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] > 0 and zlib.crc32(np.array(part, "<u4").tobytes()) == r["ids_crc32"] and r["doc_tokens"] == len(ids[r["doc_id"]])
        pieces.setdefault(r["doc_id"], []).append((r["start"], r["length"]))
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for group, ends in ((pieces, {k: len(v) for k, v in ids.items()}), (seqs, None)):
        for k, parts in group.items():
            at = 0
            for a, n in sorted(parts):
                assert a == at
                at += n
            assert at == ends[k] if ends else at <= 4096
    assert pieces.keys() == ids.keys() and packing.pack(none, path).count() == 0
    for kind in ("string", "int"):
        other = packing.pack(named.withColumn("doc_id", F.col("doc_id").cast(kind)), path)
        assert dict(other.dtypes)["doc_id"] == kind and other.agg(F.sum("length")).first()[0] == sum(map(len, ids.values()))


def test_best_windows_by_enumeration():
    rng = random.Random(3)
    for _ in range(60):
        places, costs = [0], [0]
        for _ in range(rng.randint(1, 9)):
            places.append(places[-1] + rng.randint(1, 10))
            costs.append(rng.choice([0, 4, 9]))
        n, window = len(places), 12

        def cost(ends, places=places, costs=costs):
            total, at = 0, 0
            for e in ends[:-1]:
                if places[e] - places[at] > window:
                    return None
                total += window - (places[e] - places[at]) + costs[e]
                at = e
            return total if places[ends[-1]] - places[at] <= window else None

        every = [[i for i in range(1, n - 1) if m >> i & 1] + [n - 1] for m in range(0, 1 << n, 2)]
        best = min(c for c in map(cost, every) if c is not None)
        assert cost(packing.best_windows(places, costs, window)) == best


def test_cuts_at_sentence_ends():
    ends = np.array([False, True])
    rng = random.Random(4)
    for _ in range(100):
        ids = np.array([int(rng.random() < 0.1) for _ in range(rng.randint(1, 120))])
        at, inside = packing.cut_places(ids, ends, window=20, gap=4)
        assert sorted(at.tolist()) == at.tolist() and set(at[~inside].tolist()) == {k + 1 for k in range(len(ids) - 1) if ids[k]}
        bounds = [0, *at[~inside].tolist(), len(ids)]
        for x in at[inside]:
            k = int(np.searchsorted(bounds, x))
            assert bounds[k] - bounds[k - 1] > 20
        assert np.diff([0, *at.tolist(), len(ids)]).max() <= 20


def test_windows_end_where_sentences_do(spark):
    """Only at the tail of a task, and in sentences longer than a window, is a sentence cut."""
    rng = random.Random(13)
    path = queries.tokenizer("word_bpe_49k.json")
    rows = [(i, " ".join(". ".join(prose(rng, 9).replace(".", "") for _ in range(12)) + "." for _ in range(rng.randint(1, 30)))) for i in range(70)]
    df = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    got = packing.pack(df, path, window=512).collect()
    w = packing.word_ids(path)
    ids = {i: np.frombuffer(b, "<u4") for (i, _), b in zip(rows, w.documents([t for _, t in rows]))}
    size = Counter()
    for r in got:
        size[r["sequence_id"]] += r["length"]
    inside = [r for r in got if (stop := r["start"] + r["length"]) < r["doc_tokens"] and not w.sentence_end[ids[r["doc_id"]][stop - 1]]]
    assert len(size) > 100 and len(inside) <= 10 * 4 and all(size[r["sequence_id"]] & (size[r["sequence_id"]] - 1) == 0 for r in inside)
    assert sum(512 - n for n in size.values() if n & (n - 1)) < 0.03 * sum(size.values())


def brute_simhash(text):
    w = [x for x in (text or "").encode().lower().split()]
    if not w:
        return 0
    sh = [b" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))]
    h = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash_by_brute_force(docs, none):
    rows = [(r[0], brute_simhash(r[1])) for r in fixture_rows()]
    label = {f: {f} for _, f in rows}
    for a in list(label):
        for b in list(label):
            if bin(a ^ b).count("1") <= 4 and label[a] is not label[b]:
                label[a] |= label[b]
                for x in label[b]:
                    label[x] = label[a]
    want = Counter()
    for i, f in rows:
        want[i, f"{f:016x}", min((j for j, g in rows if g in label[f] and j is not None), default=None)] += 1
    got = Counter((r["doc_id"], r["fingerprint"], r["component_id"]) for r in simhash.simhash_components(docs).collect())
    assert got == want
    assert simhash.simhash_components(none).count() == 0


def test_anchor_links_connect_as_all_pairs(spark):
    rng = random.Random(9)
    prints = {rng.getrandbits(64) for _ in range(150)}
    for p in list(prints)[:40]:  # balls of up to four changed bits, and chains
        for _ in range(6):
            q = p
            for b in rng.sample(range(64), rng.randint(1, 4)):
                q ^= 1 << b
            prints.add(q)
            p = q if rng.random() < 0.3 else p
    signed = [p - (1 << 64) if p >> 63 else p for p in prints]
    df = spark.createDataFrame([(p, p) for p in signed], "node long, w0 long")
    links = simhash.anchor_links(df, ["w0"], [(0, 0, 21), (0, 21, 21), (0, 42, 22)], 4).collect()
    mask = (1 << 64) - 1
    parent = {p: p for p in signed}

    def root(x, parent):
        while parent[x] != x:
            x = parent[x]
        return x

    for r in links:
        assert bin((r["src"] ^ r["dst"]) & mask).count("1") <= 4
        a, b = root(r["src"], parent), root(r["dst"], parent)
        parent[max(a, b)] = min(a, b)
    full = {p: p for p in signed}
    for i, a in enumerate(signed):
        for b in signed[:i]:
            if bin((a ^ b) & mask).count("1") <= 4:
                x, y = root(a, full), root(b, full)
                full[max(x, y)] = min(x, y)
    assert {p: root(p, parent) for p in signed} == {p: root(p, full) for p in signed}


def test_near_duplicates(docs, none):
    kept = {r["doc_id"] for r in simhash.one_of_each_group(docs).collect()}
    rows = {r[0]: r[1] for r in fixture_rows()}
    gone = set(rows) - kept
    assert {100, 101, 102, 103, 104} <= gone
    for i in gone:  # each has a like document of smaller id that stays, or one that leads to it
        assert any(simhash.similarity(rows[i] or "", rows[j] or "") >= 0.8 for j in rows if j is not None and i is not None and j < i)
    near = {i for i in (120, 121, 122) if simhash.similarity(rows[i], rows[7]) >= 0.8}
    assert near <= gone and simhash.one_of_each_group(none).count() == 0


def test_very_dense_anchors_keep_the_nearest():
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, 3, dtype=np.uint64)
    words = np.repeat(base[None, :] ^ (np.uint64(1) << rng.integers(0, 64, (40, 3)).astype(np.uint64)), 2, axis=0)
    got = simhash._nearest(words, np.ones(80, bool), 40, cells=400)
    assert {(i, i ^ 1) for i in range(80)} <= set(got)
    assert all(abs(i - j) < 20 for i, j in got)


def groups_by_brute_force(rows):
    sets = {i: set(simhash.shingle_hashes(simhash.tokens(t), 5).tolist()) for i, t in rows}
    up = {i: i for i in sets}

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in sets:
        for j in sets:
            if i < j and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                a, b = sorted((top(i), top(j)))
                up[b] = a
    return {i: top(i) for i in sets}


def test_prefix_pairs_miss_nothing(spark):
    rng = random.Random(8)
    sets = {}
    for k in range(60):
        own = [rng.randrange(1 << 62) for _ in range(rng.randint(1, 60))]
        sets[2 * k] = set(own)
        sets[2 * k + 1] = set(own[: max(1, len(own) * 9 // 10)]) | ({rng.randrange(50)} if k % 3 else set())
    common = np.array(sorted({x for v in list(sets.values())[:20] for x in v}), np.uint64)
    rank = np.random.default_rng(2).permutation(len(common))
    first = {i: simhash.prefix(np.array(sorted(v), np.uint64), common, rank, 0.8) for i, v in sets.items()}
    assert any(hot for _, hot in first.values()) and not all(hot for _, hot in first.values())
    rows = [(i, i, len(v), first[i][0].tobytes(), first[i][1]) for i, v in sets.items()]
    df = spark.createDataFrame(rows, "node long, own long, n int, prefix binary, common int")
    got = {tuple(r) for r in simhash.prefix_pairs(df, 0.8).collect()}
    want = {(i, j) for i in sets for j in sets if i < j and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])}
    assert len(want) > 20 and want <= got and len(got) < 200
    assert simhash.prefix_pairs(df.withColumn("own", F.lit(1).cast("long")), 0.8).count() == 0


def test_near_duplicates_of_one_vocabulary(spark):
    rng = random.Random(9)
    vocabulary = [f"w{i}" for i in range(150)]
    rows = []
    for i in range(80):  # equal sets of words, so equal fingerprints
        w = rng.sample(vocabulary, len(vocabulary))
        rows += [(i, " ".join(w)), (1000 - i, " ".join(w[10:] + w[:10]))]
    got = {r["doc"]: r["kept"] for r in simhash.near_duplicate_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == groups_by_brute_force(rows) and len(set(got.values())) == 80


def test_near_duplicates_with_block_edits(spark):
    rng = random.Random(10)
    rows = []
    for i in range(200):
        w = [f"{rng.choice(WORDS)}{rng.randrange(400)}" for _ in range(rng.randint(60, 200))]
        new = [f"new{rng.randrange(10**6)}" for _ in range(len(w) // 6)]
        edited = (w + new, w[: len(w) * 5 // 6], w[: len(w) // 2] + new[: len(w) // 12] + w[len(w) // 2 + len(w) // 12 :])[i % 3]
        rows += [(i, " ".join(w)), (1000 + i, " ".join(edited))]
    got = {r["doc"]: r["kept"] for r in simhash.near_duplicate_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    want = groups_by_brute_force(rows)
    assert got == want and len(set(want.values())) < 260


def test_near_duplicates_without_or_with_repeated_ids(spark):
    rng = random.Random(12)
    a, b, c, d, e = (prose(rng, 60) for _ in range(5))
    rows = [(None, a), (None, b), (None, c), (None, a + " end"), (1, c), (2, d), (2, e), (2, e), (3, e), (None, None), (None, None)]
    got = Counter((r["doc_id"], r["text"]) for r in simhash.one_of_each_group(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    either = got.pop((None, a), 0) + got.pop((None, a + " end"), 0)
    assert either == 1 and got == Counter([(None, b), (1, c), (2, d), (2, e), (None, None)])


def test_top_k_by_brute_force(spark):
    rng = random.Random(6)
    rows = [(i, [rng.gauss(0, 1) * (1 + i % 7) for _ in range(6)]) for i in range(230)] + [(230, None), (231, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (232, [float("nan")] * 6), (233, [float("inf")] * 6), (None, [1.0] * 6)]
    rows += [(234, rows[9][1]), (235, [0.0] * 6), (236, [1.0, 2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = Counter(tuple(r) for r in topk.top_k(df, df.where("vec_id % 10 = 0"), query_block=7, bucket=16, part_rows=50).collect())
    ok = {i: [math.floor(float(np.float32(x)) * 256) for x in v] for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)}
    want = Counter()
    for q in (i for i in ok if i % 10 == 0):
        best = sorted((-sum(a * b for a, b in zip(ok[q], v)), i) for i, v in ok.items() if i != q)[:5]
        for r, (s, i) in enumerate(best, 1):
            want[q, r, i, -s] += 1
    assert got == want
    assert topk.top_k(df.limit(0), df.limit(0)).count() == 0


def test_top_k_with_repeated_ids(spark):
    rows = [(0, [1.0, 0.5 * i]) for i in range(8)] + [(i, [float(i), 1.0]) for i in range(1, 9)] + [(50, [2.0, 2.0]), (50, [2.0, 2.0]), (3, [3.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumns({"cell": F.lit("c"), "side": F.lit(9), "v": F.lit(1.5)})
    got = Counter(tuple(r) for r in topk.top_k(df, df.where("vec_id % 50 = 0"), bucket=3).collect())
    want = Counter()
    for q, x in ((0, [1.0, 0.0]), (50, [2.0, 2.0])):
        best = sorted((-sum(int(256 * a) * int(256 * b) for a, b in zip(x, v)), i) for i, v in rows if i != q)[:5]
        want.update((q, r, i, -s) for r, (s, i) in enumerate(best, 1))
    assert got == want


def test_top_k_large_numbers(spark):
    df = spark.createDataFrame([(0, [3e9, 1.0]), (1, [2e3, 5.0]), (2, [1e3, 7.0])], "vec_id long, embedding array<double>")
    got = [(r["vec_id"], r["score"]) for r in topk.top_k(df, df.where("vec_id = 0")).orderBy("rank").collect()]
    assert got == [(1, int(3e9) * 256 * 2000 * 256 + 256 * 1280), (2, int(3e9) * 256 * 1000 * 256 + 256 * 7 * 256)]


def test_classifiers_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.1"
    labels = {r["doc_id"]: r for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    for query, field, least in ((queries.op2_toxicity, "toxic", 0.95), (queries.op8_quality, "quality", 0.97)):
        rows = [r for r in query(spark, sf).collect() if r["held_out"] and r["doc_id"] in labels]
        assert all(zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0 for r in rows)
        right = sum(r["predicted"] == labels[r["doc_id"]][field] for r in rows)
        assert right / len(rows) >= least, (field, right / len(rows))


def test_classifiers_take_any_row(spark, docs, none):
    labels = spark.createDataFrame([(i, i % 2, i % 3 == 0) for i in range(40)], "doc_id long, quality int, odd boolean")
    model = quality.learn(docs, labels)
    assert quality.score(docs, model).count() == docs.count() and quality.score(none, model).count() == 0
    assert set(quality.accepted(docs, model).columns) == set(docs.columns)
    empty = quality.learn(none, labels.limit(0))
    assert all(0 <= r["score"] <= 1 for r in quality.score(docs, empty).collect())
    machine = toxicity.learn(docs, labels, "quality")
    assert toxicity.score(docs, machine).count() == docs.count() and toxicity.score(none, machine).count() == 0
    assert toxicity.learn(none, labels.limit(0), "quality").terms.size == 0
    assert training.labelled_sample(docs, labels, "quality", max_rows=5).count() <= 5


def agreeing_rows(n, seed=8):
    """Rows that are toxic where two words agree, among others that mean nothing."""
    rng = random.Random(seed)
    rows, y = [], []
    for _ in range(n):
        a, b = rng.random() < 0.5, rng.random() < 0.5
        rows.append(sorted({*([1] if a else []), *([2] if b else []), *(rng.sample(range(10, 60), 3))}))
        y.append(int(a == b))
    return rows, np.array(y)


def test_pairs_of_terms_count():
    """Additive weights can't tell such rows apart, the pair's vectors do."""
    rows, y = agreeing_rows(600)
    m = toxicity.fit(rows, y)
    assert {1, 2} <= set(m.terms.tolist())
    more, z = agreeing_rows(400, 9)
    assert np.mean([(m.of_terms(r) >= 0.5) == t for r, t in zip(more, z)]) > 0.95
    assert m.of_terms([1, 2]) > 0.9 > 0.1 > m.of_terms([1]) and toxicity.fit(rows, np.ones(600)).terms.size == 0


def test_toxicity_scores_by_brute_force(spark, docs):
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(60)], "doc_id long, toxic int")
    marked = docs.withColumn("text", F.when(F.pmod("doc_id", F.lit(3)) == 0, F.concat(F.lit("Nastiest, "), "text")).otherwise(F.col("text")))
    m = toxicity.learn(marked, labels)
    column = {int(t): k for k, t in enumerate(m.terms)}
    assert toxicity.bucket("nastiest") in column and toxicity.bucket("nastie-") in column
    got = Counter((r["doc_id"], round(r["score"], 9), r["predicted"]) for r in toxicity.score(marked, m).collect())
    want = Counter()
    for i, t in marked.select("doc_id", "text").collect():
        own = [column[b] for b in toxicity.buckets(t or "") if b in column]
        raw = m.bias + sum(m.weights[a] for a in own) + sum(float(m.factors[a] @ m.factors[b]) for k, a in enumerate(own) for b in own[:k])
        p = 1 / (1 + math.exp(-raw))
        want[i, round(p, 9), int(p >= 0.5)] += 1
    assert got == want
    again = toxicity.learn(marked.repartition(7), labels)
    assert np.array_equal(again.terms, m.terms) and np.array_equal(again.weights, m.weights)


def statistics_by_hand(text):
    text = text or ""
    words = [w for w in re.split(r"[ \t\n\x0b\f\r]+", text) if w]
    lines = [x for x in text.split("\n") if x]
    signs = [c for c in text if c not in " \t\n\x0b\f\r"]
    import unicodedata

    kind = [unicodedata.category(c) for c in signs]
    letters, part = sum(k[0] == "L" for k in kind), lambda a, b: a / b if b else 0.0
    odd = sum(c in "%&$#*!|~^@=<>{}[]\\/_+" for c in text)
    return (
        len(words), part(len(signs), len(words)), part(letters, len(signs)), part(kind.count("Lu"), letters), part(sum(c in "0123456789" for c in text), len(signs)), part(odd, len(signs)),
        part(sum(c in ".,;:?" for c in text), len(words)), part(len(set(words)), len(words)), part(len(set(lines)), len(lines)), part(len(words), len(lines)),
    )


def test_statistics_by_brute_force(spark, docs):
    texts = [r[1] for r in fixture_rows()] + ["A! b? C;\n\nA! b? C;\n#$%&*", "x" * 300_000 + " Y\n" * 1000, "{[<|>]}\\/_+=~^@ 1234"]
    df = spark.createDataFrame([(t, "clash") for t in texts], "text string, words string")
    for t, s in quality.with_statistics(df).select("text", "__stats").collect():
        assert tuple(s) == pytest.approx(statistics_by_hand(t), abs=1e-12), (t or "")[:50]


def test_rules_are_the_columns(spark):
    rng = np.random.default_rng(4)
    x = rng.random((400, len(quality.STATISTICS)))
    y = ((x[:, 5] > 0.6) | ((x[:, 0] < 0.3) & (x[:, 2] > 0.5))).astype(int)
    m = quality.fit(x, y)
    assert ((m.of(x) > 0.5) == y).mean() > 0.97
    df = spark.createDataFrame([tuple(map(float, r)) for r in x[:50]], list(quality.STATISTICS)).select(F.struct(*quality.STATISTICS).alias("__stats"))
    assert np.allclose([r[0] for r in df.select(m.column()).collect()], m.of(x[:50]))


def test_pipeline(spark, small):
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES][1] == "SimHash near-dedup"
    docs = spark.read.parquet(f"{small}/documents.parquet")
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, small)
        if k + 1 < len(corpus_pipeline.STAGES):
            assert sorted(out.columns) == sorted(docs.columns)
            docs = spark.createDataFrame(out.toPandas(), docs.schema)
    assert out.count() > 0


def test_ids_without_places_are_the_librarys():
    """The call that follows each token's place in the text is not made, and the ids are the same."""
    import numpy as np
    import public_tokenizers
    from tokenizers import Tokenizer

    from reportgraph.llm.packing import WordIds

    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)

    class Fast:
        encode_batch_fast = library.encode_batch_fast

    words = WordIds(path)
    words.tokenizer = Fast()
    texts = ["", "a", " ", "Plain words, and  more.", "İstanbul 中文 café café Ärger! <|endoftext|> x1-2", "中文\n中文", "ẞ straße Σσς"]
    for _ in range(2):
        assert words.documents(texts) == [np.asarray(library.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts]


def test_workers_keep_nothing_of_earlier_operators():
    """A worker that has packed holds none of it when passages are sought in it, nor the words of these when they are done."""
    import public_tokenizers
    import pyarrow as pa
    from pyspark.sql.types import LongType, StringType, StructField, StructType

    from reportgraph.llm import worker

    class Rows:
        dtypes = [("__row", "bigint"), ("__doc", "bigint"), ("__text", "string")]
        schema = StructType([StructField("__row", LongType()), StructField("__doc", LongType()), StructField("__text", StringType())])

        def select(self, *names):
            return self

        def mapInArrow(self, run, schema):
            return run

    packing.word_ids(str(public_tokenizers.path("word_bpe_49k.json")))
    assert list(worker._HELD)
    text = " ".join(f"w{i}" for i in range(60)) + "."
    ids = list(range(worker.SLICE_ROWS * 2 + 1))
    batch = pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(ids, pa.int64()), pa.array([text] * len(ids))], names=["row", "doc", "text"])
    got = [b for b in substring_dedup.unit_table(Rows())(iter([batch]))]
    assert len(got) == 3 and sum(b.num_rows for b in got) == len(ids) * len(substring_dedup.units(text))
    assert list(dict.fromkeys(x for b in got for x in b.column(1).to_pylist())) == ids
    assert not worker._HELD
    substring_dedup._CUTS.clear()
    list(substring_dedup.unit_table(Rows())(iter([batch])))
    assert not substring_dedup._CUTS
