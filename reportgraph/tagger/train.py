"""Training by rounds of local steps on shards with averaged weights, and tagging of whole corpora."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType

from reportgraph.functions.vectors import word_vector
from reportgraph.operators.hot import join_hot
from reportgraph.operators.labeling import token_rows
from reportgraph.sources.io import checkpointed, stored
from reportgraph.tagger.model import Adam, Tagger

#: Sentences that ``fit_sentences`` tells, if it is not told how many; those of lowest hash.
MAX_SENTENCES = 4000
MAX_TOKENS = 300
#: Distinct examples that one shard learns from, about; its batches in an epoch, about, beyond which they hold more sentences; so many sets of weights are added up in one task.
SHARD_EXAMPLES, SHARD_BATCHES, ADDED = 2048, 256, 8
#: Fewer tagged forms of sentences than this may be broadcast.
BROADCAST_FORMS = 50_000
#: Forms that a task decodes, at least, if all cores have some.
TASK_FORMS = 2_000


def token_matrix(tokens: list[str], dim: int, table: dict[str, np.ndarray] | None = None) -> np.ndarray:
    """A token's vector of the table, else of its spelling, digits taken as one sign, so numbers of like shape are alike."""
    return np.stack([table[t.lower()] if table and t.lower() in table else word_vector(re.sub("[0-9]", "0", t), dim) for t in tokens])


def spelled(tokens: list[str], table: dict | None = None) -> tuple[str, ...]:
    """What a model sees of tokens; sentences that differ in digits alone are one to it, and are decoded once."""
    return tuple(t.lower() if table and t.lower() in table else re.sub("[0-9]", "0", t).lower() for t in tokens)


def in_windows(sequences: DataFrame, max_len: int = MAX_TOKENS, stride: int = 250) -> DataFrame:
    """Sequences of more than ``max_len`` tokens as windows that overlap, with their tags; others as they are, in window 0."""
    n = F.size("tokens")
    last = F.when(n <= max_len, 0).otherwise(F.ceil((n - max_len) / F.lit(stride)).cast("int"))
    rows = sequences.withColumn("window", F.explode(F.sequence(F.lit(0), last)))
    return rows.withColumns({c: F.slice(c, F.col("window") * stride + 1, F.lit(max_len)) for c in ("tokens", "entity_tags", "type_tags")})


def batches_by_length(pdf: pd.DataFrame, size: int) -> Iterator[pd.DataFrame]:
    """Rows of one length at a time, in a fixed order, so no padding is needed."""
    for _, part in pdf.groupby(pdf["tokens"].map(len), sort=True):
        for i in range(0, len(part), size):
            yield part.iloc[i : i + size]


def weighted_batches(pdf: pd.DataFrame, size: int) -> Iterator[tuple[pd.DataFrame, np.ndarray]]:
    """Rows of one length at a time with the number of equal sentences that each stands for: as if these stood in a line that is cut after each ``size`` of them.

    A row of many sentences is in several batches, so each sentence counts once, and equal ones of a batch are one row of it. The batches of a shard with more than
    ``SHARD_BATCHES`` of them, and with more than its distinct rows would fill, are larger.
    """
    step = max(size, pdf["n"].sum() / max(SHARD_BATCHES, len(pdf) / size))
    for _, part in pdf.groupby(pdf["tokens"].map(len), sort=True):
        stop = part["n"].to_numpy(float).cumsum()
        start = np.append(0.0, stop[:-1])
        for k in range(max(1, int(np.ceil(stop[-1] / step - 1e-9)))):
            i, j = np.searchsorted(stop, k * step, "right"), np.searchsorted(start, (k + 1) * step, "left")
            share = np.minimum(stop[i:j], (k + 1) * step) - np.maximum(start[i:j], k * step)
            if (share > 0).any():
                yield part.iloc[i:j][share > 0], share[share > 0]


def examples(sequences: DataFrame, model: Tagger) -> DataFrame:
    """``tokens, entity_tags, type_tags, n``: the distinct examples as ``model`` sees them, and of how many of ``sequences`` (each of ``n`` sentences, if it has that column) each one is."""
    n = F.sum("n") if "n" in sequences.columns else F.count("*")
    return sequences.groupBy(seen_as(model, "tokens").alias("tokens"), "entity_tags", "type_tags").agg(n.cast("long").alias("n"))


def seen_as(model: Tagger, tokens: str) -> Column:
    """What ``model`` sees of tokens, as ``spelled``."""
    vectors = model.vectors
    if not vectors:
        return F.transform(tokens, lambda t: F.translate(t, "123456789", "0" * 9))

    @F.pandas_udf("array<string>")
    def looked_up(tokens: pd.Series) -> pd.Series:
        return tokens.map(lambda t: list(spelled(t, vectors)))

    return looked_up(tokens)


def _added(sums: DataFrame, parts: int) -> list:
    """Rows ``name, shape, n, loss, flat`` of all parts added up, in tasks of ``ADDED`` of them at a time, so the driver gets that many sets of weights at most."""

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("part")
        total = sum(np.frombuffer(b, "<f8") for b in pdf["flat"])
        return pdf.iloc[:1].assign(part=pdf["part"].iloc[0] // ADDED, n=pdf["n"].sum(), loss=pdf["loss"].sum(), flat=[total.tobytes()])

    while parts > ADDED:
        sums = sums.groupBy("name", F.expr(f"part div {ADDED}")).applyInPandas(add, sums.schema)
        parts = -(-parts // ADDED)
    return sorted(sums.collect(), key=lambda r: (r["name"], r["part"]))


def fit_sentences(sentences: DataFrame, max_sentences: int = MAX_SENTENCES, reports: DataFrame | None = None) -> DataFrame:
    """Those of ``sentences`` that ``fit`` may learn from, told without their tokens: the ``max_sentences`` of lowest hash and every one that may have several windows.

    A text has at most one token more than signs, so one of fewer signs than a window's tokens is one window. With ``reports``, of unique ``report_id``,
    only their sentences count, with the other columns of the report: twice as many of lowest hash are looked up among the reports first, and all
    are joined only if too few of those are of them.
    """
    long = F.length("text") >= MAX_TOKENS
    short = sentences.where(~long).withColumn("h", F.xxhash64("report_id", "sent_no", F.lit(0)))
    lowest = lambda rows, n: rows.orderBy("h", "report_id", "sent_no").limit(n)
    first, rest = lowest(short, max_sentences), sentences.where(long)
    if reports is not None:
        tried = checkpointed(lowest(short, 2 * max_sentences))
        first = checkpointed(lowest(reports.join(F.broadcast(tried), "report_id"), max_sentences))
        if first.count() < max_sentences and tried.count() == 2 * max_sentences:
            first = lowest(short.join(reports, "report_id"), max_sentences)
        rest = rest.join(reports, "report_id")
    return checkpointed(first.drop("h").unionByName(rest))


def fit(sequences: DataFrame, model: Tagger, rounds: int = 3, shards: int = 4, batch: int = 32, rate: float = 0.02, local_epochs: int = 2, max_sentences: int | None = None) -> tuple[Tagger, list[float]]:
    """The model after ``rounds`` of averaging, and each round's mean loss.

    ``sequences`` has tokens, entity_tags and type_tags, and may have the number ``n`` of sentences that each row stands for; long ones are learned in windows.
    All are learned from, unless ``max_sentences`` says otherwise. Those that are one to the model are one example with their number, which is computed
    once for each batch that they fill. There are at least ``shards`` shards and no more than ``SHARD_EXAMPLES`` examples in one, about; their weights
    are averaged by the sentences that they stand for, and added up on the executors. Shards and batches are fixed by hash, so runs agree.
    """
    rows = in_windows(sequences.where(F.size("tokens") > 0))
    if max_sentences is not None:
        rows = rows.orderBy(F.xxhash64("report_id", "sent_no", "window"), "report_id", "sent_no", "window").limit(max_sentences)
    rows = checkpointed(examples(rows, model).withColumn("h", F.xxhash64("tokens", "entity_tags", "type_tags")))
    shards = max(shards, -(-rows.count() // SHARD_EXAMPLES))
    # A shard is a range of hashes, and the rounds read it in the same order; each is a task of its own.
    rows = rows.withColumn("shard", F.pmod("h", F.lit(shards)).cast("int"))
    fields = ("entity_tags", "type_tags")
    losses = []
    rows = rows.repartitionByRange(shards, "shard")
    for r in range(rounds):
        start = model

        def local(pdf: pd.DataFrame) -> pd.DataFrame:
            own = replace(start, weights={k: v.copy() for k, v in start.weights.items()})
            index = [{t: i for i, t in enumerate(tags)} for tags in own.tags]
            todo = []
            for part, n in weighted_batches(pdf.sort_values("h", kind="stable"), batch):
                todo.append((part["tokens"].tolist(), [np.array([[index[k].get(t, 0) for t in row] for row in part[fields[k]]]) for k in range(len(own.tags))], n))
            order, opt, total, done = np.random.default_rng(own.seed + r), Adam(rate / (1 + r)), 0.0, 0.0
            for _ in range(local_epochs):
                for i in order.permutation(len(todo)):
                    tokens, tags, n = todo[i]
                    loss, grads = own.loss_grad(np.stack([token_matrix(list(t), own.dim, own.vectors) for t in tokens]), tags, n)
                    opt.step(own.weights, grads)
                    total += loss * n.sum()
                    done += n.sum()
            part, size = int(pdf["shard"].iloc[0]), float(pdf["n"].sum())
            return pd.DataFrame([(part, k, list(np.shape(v)), size, total / max(done, 1.0) * size, (np.ravel(v) * size).astype("<f8").tobytes()) for k, v in sorted(own.weights.items())], columns=["part", "name", "shape", "n", "loss", "flat"])

        got = _added(rows.groupBy("shard").applyInPandas(local, "part long, name string, shape array<int>, n double, loss double, flat binary"), shards)
        if not got:
            break
        sums: dict[str, np.ndarray] = {}
        counts: dict[str, float] = {}
        for g in got:
            sums[g["name"]] = sums.get(g["name"], 0.0) + np.frombuffer(g["flat"], "<f8").reshape(g["shape"])
            counts[g["name"]] = counts.get(g["name"], 0.0) + g["n"]
        model = replace(model, weights={k: v / counts[k] for k, v in sums.items()})
        one = [g for g in got if g["name"] == "bias0"]
        losses.append(sum(g["loss"] for g in one) / sum(g["n"] for g in one))
    return model, losses


def attention_shares(sentences: DataFrame, model: Tagger, task: int = 0) -> DataFrame:
    """``report_id, sent_no, tokens, shares``: how much of a sentence's attention each token gets (none without attention); it is computed once for all sentences that are one to the model."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in parts:
            for part in batches_by_length(pdf.rename(columns={"form": "tokens"}), 64):
                a = None
                if len(part["tokens"].iloc[0]):
                    a = model.emissions(model.encode(np.stack([token_matrix(list(t), model.dim, model.vectors) for t in part["tokens"]]))[0], task)[2]
                yield pd.DataFrame({"form": part["tokens"], "shares": [[]] * len(part) if a is None else a.tolist(), "n": part["n"]})

    rows = stored(sentences.select("report_id", "sent_no", "tokens").withColumn("form", seen_as(model, "tokens")))
    known = _dealt(rows.groupBy("form").agg(F.count("*").alias("n"))).mapInPandas(run, "form array<string>, shares array<double>, n long")
    return _joined(rows, checkpointed(known)).select("report_id", "sent_no", "tokens", "shares")


def tag(sentences: DataFrame, model: Tagger, batch: int = 256) -> DataFrame:
    """``report_id, sent_no, tokens, starts, pred``: the best entity tags of every sentence; on a table also their ``spans``.

    Sentences beyond ``MAX_TOKENS`` tokens are tagged in pieces of that size, so none is cut off. On a stream it is a map over rows with the
    model along, in which one of the sentences of a batch that look alike to the model is decoded. On a table one of all such
    sentences is: their forms are grouped by a shuffle, decoded, and joined back.
    """
    if "starts" not in sentences.columns:
        sentences = sentences.withColumn("starts", F.transform("tokens", lambda t: F.lit(True)))
    rows = sentences.select("report_id", "sent_no", "tokens", "starts")
    if sentences.isStreaming:
        return _decoded(rows, model, batch)
    rows = stored(rows.withColumn("form", seen_as(model, "tokens")))
    counts = _dealt(rows.groupBy("form").agg(F.count("*").alias("n")))
    forms = counts.select(F.xxhash64("form").alias("report_id"), F.lit(0).alias("sent_no"), F.col("form").alias("tokens"), F.array().cast("array<boolean>").alias("starts"), "n")
    known = _decoded(forms, model, batch, "n").select(F.col("tokens").alias("form"), "pred", "n")
    rows = _joined(rows, checkpointed(with_spans(known, "pred")))
    return rows.select("report_id", "sent_no", "tokens", "starts", "pred", "spans")


def _dealt(forms: DataFrame) -> DataFrame:
    """Forms, written once and counted, in as many tasks as their work is worth: one has at least ``TASK_FORMS`` of them if all cores have some.

    A task decodes the sentences of one length together, so many small tasks would take each a few at a time.
    """
    forms = checkpointed(forms)
    spark = forms.sparkSession
    most = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return forms.repartition(min(most, max(spark.sparkContext.defaultParallelism, forms.count() // TASK_FORMS)), F.xxhash64("form"))


def _joined(rows: DataFrame, known: DataFrame) -> DataFrame:
    """Sentences with what is known of their forms, which are counted before they are broadcast."""
    if known.count() < BROADCAST_FORMS:
        return rows.join(F.broadcast(known.drop("n")), "form")
    return join_hot(rows, known, "form", ["report_id", "sent_no"], "inner")


@F.pandas_udf(ArrayType(IntegerType()))
def token_places(text: pd.Series, tokens: pd.Series) -> pd.Series:
    """Where each token of a text begins, from 0."""

    def places(t: str, found: list[str]) -> list[int]:
        out, at = [], 0
        for x in found:
            at = t.index(x, at)
            out.append(at)
            at += len(x)
        return out

    return pd.Series([places(t, list(found)) for t, found in zip(text, tokens)], dtype=object)


def _pieces(s: Column) -> Column:
    """A span's text as pieces ``at, size, lead`` of its sentence; tokens that stand as they are joined, with one blank or none between, are one piece."""
    own = F.sequence(s["begin"] + 1, s["begin"] + s["size"])  # from 1, as elements are counted
    all_ = F.transform(own, lambda i: F.struct(F.element_at("places", i).alias("at"), F.length(F.element_at("tokens", i)).alias("size"), F.element_at("starts", i).alias("lead")))
    none = F.filter(all_, lambda p: F.lit(False))

    def add(kept: Column, p: Column) -> Column:
        last = F.element_at(kept, -1)
        stop = last["at"] + last["size"]
        as_is = F.when(p["lead"], (p["at"] == stop + 1) & (F.substring("form", stop + 1, F.lit(1)) == " ")).otherwise(p["at"] == stop)
        longer = F.struct(last["at"].alias("at"), (p["at"] + p["size"] - last["at"]).alias("size"), last["lead"].alias("lead"))
        return F.when((F.size(kept) > 0) & as_is, F.concat(F.slice(kept, 1, F.size(kept) - 1), F.array(longer))).otherwise(F.concat(kept, F.array(p)))

    return F.aggregate(all_, none, add)


def text_mentions(sentences: DataFrame, model: Tagger, tokens: str = "words", batch: int = 256, written: bool = False) -> DataFrame:
    """``mentions_of(tag(token_rows(sentences)))`` of ``report_id, sent_no, text``.

    Cutting and spelling take all digits alike, so on a table the distinct texts with zeros for digits are cut and decoded, and the sentences
    take values from the places of their text's spans. Sentences that are ``written`` are not written again. A model with trained vectors tells digits apart, and a stream is a map; they go by tokens.
    """
    if sentences.isStreaming or model.vectors:
        return mentions_of(tag(token_rows(sentences, tokens), model, batch))
    rows = sentences.select("report_id", "sent_no", "text")
    rows = (rows if written else stored(rows)).withColumn("form", F.translate("text", "123456789", "0" * 9))
    counts = _dealt(rows.groupBy("form").agg(F.count("*").alias("n")).where("form IS NOT NULL"))
    forms = counts.select(F.xxhash64("form").alias("report_id"), F.lit(0).alias("sent_no"), F.col("form").alias("text"), "form", "n")
    cut = stored(token_rows(forms, tokens, ("form", "n")))
    known = cut.join(tag(cut.groupBy("tokens", "starts").agg(F.min("report_id").alias("report_id"), F.min("sent_no").alias("sent_no")), model, batch).select("tokens", "starts", "spans"), ["tokens", "starts"])
    known = known.withColumn("places", token_places("form", "tokens"))
    known = known.select("form", "n", F.transform("spans", lambda s: F.struct(s["begin"].alias("begin"), s["size"].alias("size"), s["entity"].alias("entity"), _pieces(s).alias("pieces"))).alias("spans"))
    rows = _joined(rows, checkpointed(known)).withColumn("s", F.explode("spans"))
    piece = lambda p: F.concat(F.when(p["lead"], F.lit(" ")).otherwise(F.lit("")), F.substring("text", p["at"] + 1, p["size"]))
    one = F.substring("text", F.get("s.pieces", 0)["at"] + 1, F.get("s.pieces", 0)["size"])
    value = F.when(F.size("s.pieces") == 1, one).otherwise(F.array_join(F.transform("s.pieces", piece), ""))
    return rows.select("report_id", "sent_no", "s.begin", "s.size", "s.entity", F.trim(value).alias("value"))


def _decoded(rows: DataFrame, model: Tagger, batch: int, *more: str) -> DataFrame:
    """The map over rows that ``tag`` is; of the sentences of a batch that look alike to the model one is decoded."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = np.array(model.tags[0])
        for pdf in parts:
            pieces = [(i, k, spelled(t[k : k + MAX_TOKENS], model.vectors)) for i, t in enumerate(pdf["tokens"]) for k in range(0, max(len(t), 1), MAX_TOKENS)]
            frame = pd.DataFrame({"tokens": [t for t in dict.fromkeys(t for _, _, t in pieces) if t]})
            found: dict[tuple[str, ...], list[str]] = {(): []}
            for part in batches_by_length(frame, batch):
                x = np.stack([token_matrix(t, model.dim, model.vectors) for t in part["tokens"]])
                found.update((t, tags.tolist()) for t, tags in zip(part["tokens"], names[model.decode(x)]))
            pred = [[] for _ in range(len(pdf))]
            for i, _, t in pieces:
                pred[i].extend(found[t])
            yield pd.DataFrame({"report_id": pdf["report_id"], "sent_no": pdf["sent_no"], "tokens": pdf["tokens"], "starts": pdf["starts"], "pred": pred} | {c: pdf[c] for c in more})

    schema = "report_id long, sent_no int, tokens array<string>, starts array<boolean>, pred array<string>" + "".join(f", {c} long" for c in more)
    return rows.select("report_id", "sent_no", "tokens", "starts", *more).mapInPandas(run, schema)


def with_spans(tagged: DataFrame, tags_col: str) -> DataFrame:
    """Adds ``spans``, begin, size and entity of the runs of begin/inside tags; an inside tag after another entity begins a span."""
    ent = F.transform(tags_col, lambda t: F.when(t == "O", F.lit(None).cast("string")).otherwise(F.substring(t, F.lit(3), F.length(t))))
    g, rows = F.col(tags_col), tagged.withColumn("__e", ent)
    starts = lambda i: F.coalesce(F.get(g, i).startswith("B-"), F.lit(True)) | ~F.get("__e", i - 1).eqNullSafe(F.get("__e", i))
    # A run ends where the next one starts or an outside tag or nothing follows.
    stops = F.filter(F.sequence(F.lit(0), F.size(g)), lambda i: (i == F.size(g)) | (i == 0) | starts(i))
    rows = rows.withColumn("__at", F.when(F.size(g) > 0, stops).otherwise(F.array().cast("array<int>")))
    runs = F.transform("__at", lambda b, k: F.struct(b.alias("begin"), (F.get("__at", k + 1) - b).alias("size"), F.get("__e", b).alias("entity")))
    return rows.withColumn("spans", F.filter(runs, lambda s: s["entity"].isNotNull())).drop("__e", "__at")


def mentions_of(tagged: DataFrame, tags_col: str = "pred") -> DataFrame:
    """Spans ``report_id, sent_no, begin, size, entity, value`` of begin/inside tags; an inside tag after another entity begins a span.

    With a column ``starts`` values have blanks only where the sentence has them, else between all tokens. Spans that ``tag`` has found for a
    form are not sought again in each of its sentences.
    """
    rows = tagged if tags_col == "pred" and "spans" in tagged.columns else with_spans(tagged, tags_col)
    blank = F.slice("starts", F.col("s.begin") + 1, F.col("s.size")) if "starts" in tagged.columns else F.array_repeat(F.lit(True), F.col("s.size"))
    some = F.slice("tokens", F.col("s.begin") + 1, F.col("s.size"))
    words = F.zip_with(some, blank, lambda t, first: F.when(first, F.concat(F.lit(" "), t)).otherwise(t))
    rows = rows.withColumn("s", F.explode("spans"))
    return rows.select("report_id", "sent_no", "s.begin", "s.size", "s.entity", F.trim(F.array_join(words, "")).alias("value"))
