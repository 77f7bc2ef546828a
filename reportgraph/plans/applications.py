"""Taggers, title clusters, recommendation, routing, measures, service and streams as queries."""

from __future__ import annotations

import functools
import inspect

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reportgraph.functions import text as T
from reportgraph.functions.vectors import VectorFiles, train_word2vec, vector_table
from reportgraph.operators import graph, labeling, metrics, propagate, recommend, relations, service, titles, triage
from reportgraph.plans.mining import TRUE_PAIRS, mined, rounded, state_of
from reportgraph.plans.oracles import chain
from reportgraph.sources import corpus
from reportgraph.sources.io import checkpointed, read_table, stored
from reportgraph.streaming.streams import STREAMS, auto_trigger
from reportgraph.tagger import model as tagger
from reportgraph.tagger import train

QUERIES: dict[str, tuple] = {}


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = (query, sql)


_KEPT: dict[tuple, object] = {}


def kept(f):
    """Keeps a result for the session and folder; an option that is left out is the same as its default."""
    options = list(inspect.signature(f).parameters.values())[2:]

    @functools.wraps(f)
    def once(spark: SparkSession, sf_dir: str, *args):
        full = (*args, *(p.default for p in options[len(args) :]))
        key = (f.__name__, spark.sparkContext.applicationId, sf_dir, state_of(spark, sf_dir), *full)
        if key not in _KEPT:
            _KEPT[key] = f(spark, sf_dir, *args)
        return _KEPT[key]

    return once


# --- taggers: labels from the patterns and propagation, test reports strictly later
#: Published widths of word vectors and of each direction's cells.
DIM, HIDDEN = 100, 200
#: Sizes of the ablations, which train several models each.
SMALL = (32, 24)
ROUNDS = 2


@kept
def report_heads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All reports without their texts."""
    return stored(corpus.order_reports(spark, sf_dir).drop("description"))


@kept
def report_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``report_id, part``: all reports, split in time."""
    return stored(labeling.temporal_split(report_heads(spark, sf_dir).select("report_id", "modified_at"), "modified_at").select("report_id", "part"))


@kept
def split_sentences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All sentences, split in time by ``part``."""
    return stored(mined(spark, sf_dir).sentences.join(report_parts(spark, sf_dir), "report_id"))


def with_spans(spark: SparkSession, sf_dir: str, part: str) -> DataFrame:
    """All sentences of one part, with the places of their mentions."""
    m = mined(spark, sf_dir)
    some = m.sentences.join(report_parts(spark, sf_dir).where(F.col("part") == part), "report_id")
    placed = propagate.seed_places(m.seeds, some).unionByName(m.propagated.join(report_parts(spark, sf_dir).where(F.col("part") == part), "report_id", "left_semi"))
    return some.join(labeling.sentence_spans(placed, m.value_types), ["report_id", "sent_no"], "left")


@kept
def sequences(spark: SparkSession, sf_dir: str, tokens: str = "words", part: str = "test") -> DataFrame:
    """Tag sequences of all sentences of one part."""
    return stored(labeling.encode_spans(with_spans(spark, sf_dir, part), tokens=tokens, keep=("part",)))


@kept
def lessons(spark: SparkSession, sf_dir: str, digits: bool = False) -> DataFrame:
    """All sentences of the earlier reports with the places of their mentions; equal ones are one row and ``n``. Without ``digits`` each one is zero, as for a model without trained vectors."""
    text = F.col("text") if digits else F.translate("text", "123456789", "0" * 9)
    rows = with_spans(spark, sf_dir, "train").groupBy(text.alias("text"), "spans").agg(F.count("*").alias("n"))
    return stored(rows.select(F.xxhash64("text", "spans").alias("report_id"), F.lit(0).alias("sent_no"), "text", "spans", "n"))


@kept
def trained_vectors(spark: SparkSession, sf_dir: str, dim: int = DIM) -> VectorFiles:
    """Word vectors of the tokens of the earlier reports."""
    rows = labeling.token_rows(split_sentences(spark, sf_dir).where("part = 'train'")).select(F.transform("tokens", F.lower).alias("tokens"))
    return vector_table(train_word2vec(rows, dim=dim, min_count=3))


@kept
def fitted(spark: SparkSession, sf_dir: str, kind: str, tokens: str = "words", weight: float = 0.5, small: bool = False, vectors: bool = False) -> tuple[tagger.Tagger, list[float]]:
    types = mined(spark, sf_dir).value_types.collect()  # at most K rows
    ent = ("O", *[f"{p}-{e}" for e in sorted(r["entity"] for r in types) for p in "BI"])
    typ = ("O", *[f"{p}-{t}" for t in sorted({r["value_type"] for r in types}) for p in "BI"])
    dim, hidden = SMALL if small else (DIM, HIDDEN)
    table = trained_vectors(spark, sf_dir, dim) if vectors else None
    make = {
        "plain": lambda: tagger.plain_tagger(dim, hidden, ent, vectors=table),
        "attention": lambda: tagger.attention_tagger(dim, hidden, ent, vectors=table),
        "joint": lambda: tagger.joint_tagger(dim, hidden, ent, typ, loss_weights=(1.0, weight), vectors=table),
    }[kind]
    rate = 0.02 if small else 0.005
    return train.fit(labeling.encode_spans(lessons(spark, sf_dir, vectors), tokens=tokens, keep=("n",)), make(), rounds=ROUNDS, rate=rate)


@kept
def predicted(spark: SparkSession, sf_dir: str, kind: str, tokens: str = "words", weight: float = 0.5, small: bool = False, vectors: bool = False) -> DataFrame:
    test = sequences(spark, sf_dir, tokens, "test")
    got = train.tag(test, fitted(spark, sf_dir, kind, tokens, weight, small, vectors)[0])
    return checkpointed(test.join(got.select("report_id", "sent_no", "pred"), ["report_id", "sent_no"]))


def tag_scores(spark: SparkSession, sf_dir: str, kind: str, *options) -> DataFrame:
    rows = predicted(spark, sf_dir, kind, *options)
    z = F.explode(F.arrays_zip(F.col("entity_tags").alias("gold"), F.col("pred").alias("pred")))
    pairs = rows.select(z.alias("z")).select(F.regexp_replace("z.gold", "^[BI]-", "").alias("gold"), F.regexp_replace("z.pred", "^[BI]-", "").alias("pred"))
    return metrics.per_type(pairs)


def compared(spark: SparkSession, sf_dir: str, models: dict[str, tuple]) -> DataFrame:
    """Averages of models on the later reports."""
    rows = [metrics.averages(tag_scores(spark, sf_dir, *options)).withColumn("model", F.lit(name)) for name, options in models.items()]
    return rounded(functools.reduce(DataFrame.unionByName, rows))


for _kind in ("plain", "attention", "joint"):
    add(f"tagger_{_kind}", lambda s, d, k=_kind: rounded(tag_scores(s, d, k)))
add("tagger_eval", lambda s, d: compared(s, d, {k: (k,) for k in ("plain", "attention", "joint")}))
add("tagger_trained_vectors", lambda s, d: compared(s, d, {"spelling": ("joint",), "trained": ("joint", "words", 0.5, False, True)}))
add("ablation_separators", lambda s, d: compared(s, d, {t: ("joint", t, 0.5, True) for t in ("words", "no separators", "blanks")}))
add("ablation_loss_weights", lambda s, d: compared(s, d, {f"{w}": ("joint", "words", w, True) for w in (0.0, 0.25, 0.5, 1.0)}))
add("tagger_errors", lambda s, d: metrics.error_examples(train.mentions_of(predicted(s, d, "joint"), "entity_tags"), train.mentions_of(predicted(s, d, "joint"))))
add("tagger_spans", lambda s, d: rounded(metrics.span_prf(train.mentions_of(predicted(s, d, "joint"), "entity_tags"), train.mentions_of(predicted(s, d, "joint")))))
add("tagger_loss", lambda s, d: s.createDataFrame([(k, i, round(x, 6)) for k in ("plain", "attention", "joint") for i, x in enumerate(fitted(s, d, k)[1])], "model string, round int, loss double"))
add("attention_shares", lambda s, d: rounded(train.attention_shares(labeling.token_rows(split_sentences(s, d).where("part = 'test'")), fitted(s, d, "joint")[0]).select("report_id", "sent_no", F.explode(F.arrays_zip("tokens", "shares")).alias("z")).select("report_id", "sent_no", F.col("z.tokens").alias("token"), F.col("z.shares").alias("share"))))


# --- relations and graph from what the trained tagger finds
@kept
def model_mentions(spark: SparkSession, sf_dir: str, small: bool = False) -> DataFrame:
    """Mentions that the joint tagger finds in all reports, in patterns and in prose alike."""
    return stored(train.text_mentions(mined(spark, sf_dir).sentences, fitted(spark, sf_dir, "joint", "words", 0.5, small)[0], written=True))


@kept
def model_relations(spark: SparkSession, sf_dir: str, small: bool = False) -> DataFrame:
    m = model_mentions(spark, sf_dir, small)
    scored = relations.score(relations.with_frequencies(relations.pairs(m), relations.frequencies(m)))
    return checkpointed(scored.select("e1", "e2", "f1", "f2", "f_joint", "total", "npmi"))


def model_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph.type_graph(relations.keep(model_relations(spark, sf_dir)))


def _model_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of the gold mentions that the tagger finds in the later reports, by place."""
    # No sentence's text is needed here: the later reports that have any are enough, and the others are left out before the lines are made and the mentions are compared.
    test = report_parts(spark, sf_dir).where("part = 'test'").select("report_id").distinct()
    test = checkpointed(test.join(mined(spark, sf_dir).sentences.select("report_id"), "report_id", "left_semi"))
    gold = corpus.order_reports_gold(spark, sf_dir, test).groupBy("report_id", "place", "entity", "value").agg(F.count("*").alias("g"))
    found = model_mentions(spark, sf_dir).select("report_id", "entity", "value").join(test, "report_id", "left_semi").distinct().withColumn("f", F.lit(1))
    rows = gold.join(found, ["report_id", "entity", "value"], "left")
    return rounded(rows.groupBy("place").agg(F.sum("g").alias("gold"), F.sum(F.when(F.col("f").isNotNull(), F.col("g")).otherwise(0)).alias("found")).withColumn("recall", F.col("found") / F.col("gold")))


def _model_pair_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    good = F.concat_ws("|", "e1", "e2").isin(*["|".join(p) for p in TRUE_PAIRS])
    ranked = model_relations(spark, sf_dir).withColumn("rank", F.row_number().over(Window.orderBy(F.desc("f_joint"), "e1", "e2"))).select("rank", good.alias("is_valid"))
    return rounded(metrics.precision_at(ranked, metrics.PAIR_RANKS))


def _model_graph_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    nodes, edges = graph.full_graph(report_heads(spark, sf_dir), model_mentions(spark, sf_dir), relations.keep(model_relations(spark, sf_dir)))
    count = lambda df, what: df.groupBy("kind").agg(F.count("*").alias("n")).withColumn("what", F.lit(what))
    return count(nodes, "node").unionByName(count(edges, "edge"))


add("model_mentions", lambda s, d: model_mentions(s, d).groupBy("entity").agg(F.count("*").alias("mentions")))
add("model_recall", _model_recall)
add("model_pair_npmi", lambda s, d: rounded(model_relations(s, d)))
add("model_pair_precision", _model_pair_precision)
add("model_type_graph", lambda s, d: rounded(model_graph(s, d)))
add("model_cliques", lambda s, d: rounded(graph.maximal_cliques(model_graph(s, d))))
add("model_full_graph_counts", _model_graph_counts)
add("model_recommended_entities", lambda s, d: rounded(_model_recommended(s, d)))


def _model_recommended(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recommendations for the title clusters over the graph of the tagger's relations."""
    g = checkpointed(model_graph(spark, sf_dir))
    first = checkpointed(recommend.primary(recommend.cluster_entities(model_mentions(spark, sf_dir), title_clusters(spark, sf_dir)), g))
    return recommend.top_k(first, recommend.relation_scores(first, g))


# --- titles and recommendation


@kept
def title_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return checkpointed(titles.embed(titles.distinct_titles(report_heads(spark, sf_dir)), dim=100))


#: Neighbours of the k-distance curve, which is also the least weight around a core.
NEAR = 4


@kept
def title_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``report_id, cluster_id`` of all reports, by their titles."""
    pts = title_points(spark, sf_dir)
    eps = titles.elbow(titles.k_distances(pts, NEAR)).first()["eps"]
    c = titles.dbscan(pts, max(float(eps or 0), 1e-6), NEAR, weight_col="weight")
    named = pts.select("id", "title").join(c, "id")
    reports = report_heads(spark, sf_dir).select("report_id", F.lower(F.trim(F.regexp_replace("title", r"\s+", " "))).alias("title"))
    return checkpointed(reports.join(named, "title").select("report_id", "cluster_id"))


def _emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vector"))


def page_title_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters of the titles of web pages, which repeat."""
    title = F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1)
    pages = read_table(spark, sf_dir, "pages").select(F.col("page_id").alias("report_id"), T.strip_markup(title).alias("title"))
    pts = checkpointed(titles.embed(titles.distinct_titles(pages), dim=100))
    eps = titles.elbow(titles.k_distances(pts, NEAR)).first()["eps"]
    return titles.dbscan(pts, max(float(eps or 0), 1e-6), NEAR, weight_col="weight").join(pts.select("id", "weight"), "id")


_E = "e AS (SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings)"
_PAIRS = f"{_E}, d AS (SELECT a.id AS a, b.id AS b, list_distance(a.v, b.v) AS d FROM e a JOIN e b ON a.id <> b.id)"
EPS, MIN_PTS = 1.06, 2
add("k_distances", lambda s, d: rounded(titles.k_distances(_emb(s, d), 3), 5), f"WITH {_PAIRS} SELECT a AS id, round(d, 5) AS k_distance FROM d QUALIFY row_number() OVER (PARTITION BY a ORDER BY d) = 3")
add("k_distance_elbow", lambda s, d: rounded(titles.elbow(titles.k_distances(_emb(s, d), 3))))
add("eps_neighbours", lambda s, d: rounded(titles.neighbour_pairs(_emb(s, d), EPS), 5), f"WITH {_PAIRS} SELECT a, b, round(d, 5) AS distance FROM d WHERE a < b AND d <= {EPS}")
add("dbscan_embeddings", lambda s, d: titles.dbscan(_emb(s, d), EPS, MIN_PTS), f"""WITH RECURSIVE {_PAIRS}, near AS (SELECT * FROM d WHERE d <= {EPS}), core AS (SELECT a AS id FROM near GROUP BY a HAVING count(*) + 1 >= {MIN_PTS}),
 reach AS (SELECT id, id AS other FROM core UNION SELECT r.id, n.b FROM reach r JOIN near n ON r.other = n.a JOIN core c ON c.id = n.b), cl AS (SELECT id, min(other) AS cluster_id FROM reach GROUP BY id),
 border AS (SELECT n.a AS id, arg_min(cluster_id, (n.d, n.b)) AS cluster_id FROM near n JOIN cl ON n.b = cl.id WHERE n.a NOT IN (SELECT id FROM core) GROUP BY n.a)
 SELECT e.id, coalesce(cl.cluster_id, border.cluster_id, -1) AS cluster_id FROM e LEFT JOIN cl ON e.id = cl.id LEFT JOIN border ON e.id = border.id""")
#: The templates of the titles are the clusters to be found; a cluster is named by the first report of its first title.
_OF_TITLE = "topic AS (SELECT k AS report_id, min(k) OVER (PARTITION BY k % 6) AS cluster_id FROM base)"
add("title_clusters", lambda s, d: title_clusters(s, d), chain("SELECT report_id, cluster_id FROM topic", _OF_TITLE))
add("eps_neighbours_hashed", lambda s, d: titles.neighbour_pairs_hashed(_emb(s, d), EPS).agg(F.count("*").alias("found")).crossJoin(titles.neighbour_pairs(_emb(s, d), EPS).agg(F.count("*").alias("pairs"))))
add("dbscan_titles_hashed", lambda s, d: titles.dbscan(title_points(s, d), float(titles.elbow(titles.k_distances(title_points(s, d), NEAR)).first()["eps"]), NEAR, weight_col="weight", method="hashed").groupBy("cluster_id").agg(F.count("*").alias("titles")), chain("SELECT cluster_id, 5::BIGINT AS titles FROM topic GROUP BY cluster_id", _OF_TITLE))
add("page_title_clusters", lambda s, d: page_title_clusters(s, d).groupBy("cluster_id").agg(F.count("*").alias("titles"), F.sum("weight").alias("pages")))
add("dbscan_titles", lambda s, d: title_clusters(s, d).groupBy("cluster_id").agg(F.count("*").alias("reports")), chain("SELECT cluster_id, count(*) AS reports FROM topic GROUP BY cluster_id", _OF_TITLE))
add("dbscan_titles_summary", lambda s, d: rounded(metrics.cluster_summary(title_clusters(s, d).withColumn("topic", F.col("report_id") % 6), "topic")), chain("SELECT count(DISTINCT cluster_id) AS clusters, 0.0::DOUBLE AS noise_share, 1.0::DOUBLE AS purity FROM topic", _OF_TITLE))
_TOPIC = _OF_TITLE + ", tops AS (SELECT cluster_id, entity, count(*) AS freq, row_number() OVER (PARTITION BY cluster_id ORDER BY count(*) DESC, entity)::INTEGER AS rank FROM mentions JOIN topic USING (report_id) GROUP BY cluster_id, entity QUALIFY rank <= 5)"
_PRIM = "prim AS (SELECT cluster_id, arg_min(entity, rank) AS entity FROM tops WHERE entity IN (SELECT src FROM two_way) GROUP BY cluster_id)"
add("cluster_top_entities", lambda s, d: recommend.cluster_entities(mined(s, d).mentions, title_clusters(s, d)), chain("SELECT cluster_id, rank, entity, freq FROM tops", _TOPIC))
add("frequency_only_ranking", lambda s, d: recommend.frequency_only(mined(s, d).mentions, title_clusters(s, d), 10), chain("SELECT cluster_id, row_number() OVER (PARTITION BY cluster_id ORDER BY count(*) DESC, entity)::INTEGER AS rank, entity, count(*) AS freq FROM mentions JOIN topic USING (report_id) GROUP BY cluster_id, entity QUALIFY rank <= 10", _TOPIC))


@kept
def _primaries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return checkpointed(recommend.primary(recommend.cluster_entities(mined(spark, sf_dir).mentions, title_clusters(spark, sf_dir)), mined(spark, sf_dir).edges))


@kept
def _scores(spark: SparkSession, sf_dir: str, denominator: str = "edges") -> DataFrame:
    return checkpointed(recommend.relation_scores(_primaries(spark, sf_dir), mined(spark, sf_dir).edges, denominator))


add("primary_entities", _primaries, chain("SELECT cluster_id, entity FROM prim", _TOPIC, _PRIM))
_WALKS = "walk AS (SELECT DISTINCT entity AS source, entity AS target, 0 AS hops, 0.0::DOUBLE AS total, [entity] AS path FROM prim UNION ALL SELECT source, b.dst, hops + 1, total + weight, list_append(path, b.dst) FROM walk w JOIN two_way b ON w.target = b.src WHERE NOT list_contains(path, b.dst))"
_BEST = "best AS (SELECT source, target, hops, total FROM walk QUALIFY row_number() OVER (PARTITION BY source, target ORDER BY hops, -total / greatest(hops, 1), path) = 1)"
for _den, _plus in (("edges", 0), ("nodes", 1)):
    add("relation_scores" + ("" if _den == "edges" else "_by_nodes"), lambda s, d, x=_den: rounded(_scores(s, d, x)), chain(f'SELECT source AS "primary", target AS entity, round(CASE WHEN hops = 0 THEN 1.0 ELSE total / (hops + {_plus}) END, 6) AS score FROM best', _TOPIC, _PRIM, _WALKS, _BEST))
add("recommended_entities", lambda s, d: rounded(recommend.top_k(_primaries(s, d), _scores(s, d))), chain("SELECT cluster_id, row_number() OVER (PARTITION BY cluster_id ORDER BY CASE WHEN hops = 0 THEN 1.0 ELSE total / hops END DESC, target)::INTEGER AS rank, target AS entity, round(CASE WHEN hops = 0 THEN 1.0 ELSE total / hops END, 6) AS score FROM prim JOIN best ON prim.entity = best.source QUALIFY rank <= 5", _TOPIC, _PRIM, _WALKS, _BEST))


def _title_recommendations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """New titles to the nearest cluster's stored list."""
    pts = title_points(spark, sf_dir)
    centres = recommend.centroids(pts, title_clusters(spark, sf_dir).withColumnRenamed("report_id", "id"))
    return recommend.nearest_cluster(pts, centres).join(recommend.top_k(_primaries(spark, sf_dir), _scores(spark, sf_dir)), "cluster_id").select("id", "cluster_id", "rank", "entity")


add("title_recommendations", _title_recommendations, chain(f"SELECT n.k AS id, n.cluster_id, row_number() OVER (PARTITION BY n.k ORDER BY CASE WHEN hops = 0 THEN 1.0 ELSE total / hops END DESC, target)::INTEGER AS rank, target AS entity FROM (SELECT min(k) AS k, min(cluster_id) AS cluster_id FROM (SELECT k, {corpus.TITLE} AS title FROM base) b JOIN topic ON topic.report_id = b.k GROUP BY title) n JOIN prim ON prim.cluster_id = n.cluster_id JOIN best ON prim.entity = best.source QUALIFY rank <= 5", _TOPIC, _PRIM, _WALKS, _BEST))


def _nearest_centroid(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _emb(spark, sf_dir)
    c = read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("label").alias("cluster_id"))
    return rounded(recommend.nearest_cluster(e, recommend.centroids(e, c)), 5)


add("nearest_centroid", _nearest_centroid, "WITH x AS (SELECT vec_id AS id, label, unnest(embedding::DOUBLE[]) AS x, unnest(range(0, len(embedding))) AS i FROM embeddings), m AS (SELECT label, i, avg(x) AS x FROM x GROUP BY ALL), c AS (SELECT label, list(x ORDER BY i) AS c FROM m GROUP BY label), d AS (SELECT vec_id AS id, label AS l2, list_distance(embedding::DOUBLE[], c.c) AS d FROM embeddings, (SELECT label AS cl, c FROM c) c, (SELECT 1) WHERE true) SELECT id, arg_min(cl, (d, cl)) AS cluster_id, round(min(d), 5) AS distance FROM (SELECT vec_id AS id, cl, list_distance(embedding::DOUBLE[], c) AS d FROM embeddings, (SELECT label AS cl, c FROM c)) GROUP BY id")

# --- routing
_TOP = f"WITH {corpus.REPORTS_SQL}, tops AS (SELECT team FROM reports WHERE resolved GROUP BY team ORDER BY count(*) DESC, team LIMIT 10), sampled AS (SELECT * FROM reports WHERE resolved AND team IN (SELECT team FROM tops) AND report_id % 5 = 0)"
add("triage_sample", lambda s, d: triage.sample(corpus.order_reports(s, d)).select("report_id", "team"), f"{_TOP} SELECT report_id, team FROM sampled")
add("triage_entity_kinds", lambda s, d: triage.entity_kind(mined(s, d).mentions, mined(s, d).value_types),
    chain("SELECT entity, words::INTEGER AS words, round(share, 6) AS distinct_share, CASE WHEN (value_type IN ('Alphabetical', 'Other') AND words > 3) OR share > 0.5 THEN 'descriptive' ELSE 'categorical' END AS kind FROM (SELECT entity, quantile_disc(len(string_split(value, ' ')), 0.5) AS words, count(DISTINCT value) / count(*) AS share FROM mentions GROUP BY entity) JOIN vtypes USING (entity)"))


@kept
def routing_inputs(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """What all feature sets read: the sampled reports, their mentions, and the kinds of entities."""
    reports = checkpointed(triage.sample(corpus.order_reports(spark, sf_dir)))
    m = mined(spark, sf_dir).mentions
    kinds = checkpointed(triage.entity_kind(m, mined(spark, sf_dir).value_types))
    return reports, checkpointed(m.join(reports.select("report_id"), "report_id", "left_semi")), kinds


@kept
def routing_rows(spark: SparkSession, sf_dir: str, feature_set: str) -> DataFrame:
    return checkpointed(triage.features(checkpointed(triage.raw_features(*routing_inputs(spark, sf_dir), feature_set))))


def triage_accuracy(spark: SparkSession, sf_dir: str, model: str, folds: tuple[int, ...] | None) -> DataFrame:
    """Accuracy of a model for each feature set, and the differences from text alone."""
    out = None
    for fs in triage.FEATURE_SETS:
        row = triage.cross_validate(routing_rows(spark, sf_dir, fs), model, only=folds).agg((F.sum("correct") / F.sum("rows")).alias("accuracy"), F.sum("rows").alias("rows")).withColumn("features", F.lit(fs))
        out = row if out is None else out.unionByName(row)
    base = F.first(F.when(F.col("features") == "text", F.col("accuracy")), ignorenulls=True).over(Window.partitionBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return rounded(out.withColumn("delta_pct", metrics.delta_pct(base, F.col("accuracy"), "symmetric")))


for _m in triage.MODELS:
    add(f"triage_{_m}", lambda s, d, m=_m: triage_accuracy(s, d, m, None))
add("triage_cv", lambda s, d: triage_accuracy(s, d, "knn", None))
add("triage_knn_hashed", lambda s, d: triage_accuracy(s, d, "knn_hashed", None))


@kept
def quality_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A second task: labelled documents by their quality, from the words alone."""
    docs = read_table(spark, sf_dir, "documents").join(read_table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    rows = docs.select(F.col("doc_id").alias("report_id"), F.col("quality").cast("string").alias("team"), "text")
    none = F.array().cast("array<string>")
    return checkpointed(triage.features(rows.select("report_id", "team", F.col("text").alias("words"), F.lit("").alias("described"), none.alias("entries"))))


def triage_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five-fold accuracy of each model on the documents' quality, and that of always naming the usual class."""
    rows = quality_rows(spark, sf_dir)
    usual = rows.groupBy("label").agg(F.count("*").alias("n")).agg((F.max("n") / F.sum("n")).alias("accuracy"), F.sum("n").alias("rows")).withColumn("model", F.lit("usual class"))
    out = [triage.cross_validate(rows, m).agg((F.sum("correct") / F.sum("rows")).alias("accuracy"), F.sum("rows").alias("rows")).withColumn("model", F.lit(m)) for m in triage.MODELS]
    return rounded(functools.reduce(DataFrame.unionByName, out, usual))


add("triage_documents", triage_documents)
add("triage_importances", lambda s, d: rounded(triage.importances(routing_rows(s, d, "entities+title"))))
add("knn_exact", lambda s, d: _knn(s, d), f"WITH {_PAIRS}, near AS (SELECT a, b FROM d QUALIFY row_number() OVER (PARTITION BY a ORDER BY d, b) <= 5), v AS (SELECT a AS id, label, count(*) AS c FROM near JOIN embeddings ON b = vec_id GROUP BY ALL) SELECT id, arg_min(label, (-c, label)) AS prediction FROM v GROUP BY id")


def _knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Majority label of the five nearest embeddings, itself left out (ties: the smaller label)."""
    near = titles.nearest(_emb(spark, sf_dir), 5)
    votes = near.join(read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("other"), "label"), "other").groupBy("id", "label").agg(F.count("*").alias("c"))
    return votes.groupBy("id").agg(F.min(F.struct((-F.col("c")).alias("c"), "label"))["label"].alias("prediction"))


add("nb_gaussian_stats", lambda s, d: rounded(read_table(s, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("mean"), F.var_samp(F.col("x").cast("double")).alias("variance"), F.count("*").alias("n"))),
    "WITH x AS (SELECT label, unnest(embedding)::DOUBLE AS x, unnest(range(0, len(embedding)))::INTEGER AS i FROM embeddings) SELECT label, i, round(avg(x), 6) AS mean, round(var_samp(x), 6) AS variance, count(*) AS n FROM x GROUP BY label, i")

# --- measures on literal and given rows
def _delta_pct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Differences of the mean prices of open and filled orders, by priority."""
    mean = lambda status: F.avg(F.when(F.col("o_orderstatus") == status, F.col("o_totalprice")))
    rows = read_table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(mean("O").alias("a"), mean("F").alias("b"))
    return rounded(rows.select("o_orderpriority", "a", "b", metrics.delta_pct(F.col("a"), F.col("b")).alias("relative"), metrics.delta_pct(F.col("a"), F.col("b"), "symmetric").alias("symmetric")))


add("delta_pct", _delta_pct, "SELECT o_orderpriority, round(a, 6) AS a, round(b, 6) AS b, round(100 * (b - a) / a, 6) AS relative, round(200 * (b - a) / (a + b), 6) AS symmetric FROM (SELECT o_orderpriority, avg(o_totalprice) FILTER (o_orderstatus = 'O') AS a, avg(o_totalprice) FILTER (o_orderstatus = 'F') AS b FROM orders GROUP BY o_orderpriority)")
#: Ranks and numbers of valid types that the published curve stands for.
TYPE_HITS = ((1, 1), (5, 5), (10, 10), (20, 20), (35, 34), (50, 48), (75, 64), (100, 77))
_INVALID = [r for (a, x), (b, y) in zip(TYPE_HITS, TYPE_HITS[1:]) for r in range(b - ((b - a) - (y - x)) + 1, b + 1)]
add("precision_drop", lambda s, d: rounded(metrics.precision_drop(metrics.precision_at(s.range(1, 101).select(F.col("id").alias("rank"), (~F.col("id").isin(*_INVALID)).alias("is_valid")), metrics.TYPE_RANKS))),
    f"SELECT 100::INTEGER AS n, round(1 - count(*) FILTER (r NOT IN ({', '.join(map(str, _INVALID))})) / 100, 6) AS precision_drop FROM range(1, 101) t(r)")
_TAGS = "SELECT o_orderpriority AS gold, CASE WHEN o_orderkey % 7 = 0 THEN 'O' WHEN o_orderkey % 11 = 0 THEN '1-URGENT' ELSE o_orderpriority END AS pred FROM orders"


def _tag_rows(s: SparkSession, d: str) -> DataFrame:
    """Priorities with fixed mistakes, as tags."""
    k = F.col("o_orderkey")
    return read_table(s, d, "orders").select(F.col("o_orderpriority").alias("gold"), F.when(k % 7 == 0, "O").when(k % 11 == 0, "1-URGENT").otherwise(F.col("o_orderpriority")).alias("pred"))


_PRF = f"t AS ({_TAGS}), g AS (SELECT gold AS tag, count(*) AS support, count(*) FILTER (gold = pred) AS tp FROM t GROUP BY gold), p AS (SELECT pred AS tag, count(*) AS given FROM t GROUP BY pred), s AS (SELECT tag, tp, given - tp AS fp, support - tp AS fn, tp / given AS precision, tp / support AS recall, support FROM g JOIN p USING (tag)), f AS (SELECT *, 2 * precision * recall / (precision + recall) AS f1 FROM s)"
add("tag_prf", lambda s, d: rounded(metrics.per_type(_tag_rows(s, d))), f"WITH {_PRF} SELECT tag, tp, fp, fn, round(precision, 6) AS precision, round(recall, 6) AS recall, round(f1, 6) AS f1, support FROM f")
add("macro_weighted_f1", lambda s, d: rounded(metrics.averages(metrics.per_type(_tag_rows(s, d)))), f"WITH {_PRF} SELECT round(avg(precision), 6) AS macro_precision, round(avg(recall), 6) AS macro_recall, round(avg(f1), 6) AS macro_f1, round(sum(f1 * support) / sum(support), 6) AS weighted_f1 FROM f")
add("reassignment_rate", lambda s, d: rounded(metrics.reassignment_rate(read_table(s, d, "events"), "user_id", "ts", "event_type", "event_id")), "WITH s AS (SELECT user_id, (lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) <> event_type)::INTEGER AS moved FROM events), i AS (SELECT user_id, sum(coalesce(moved, 0)) AS moves, count(*) AS steps FROM s GROUP BY user_id) SELECT count(*) AS items, round(avg((moves > 0)::INTEGER), 6) AS reassigned_share, round(sum(moves) / sum(steps), 6) AS move_share FROM i")
add("time_to_engage", lambda s, d: rounded(metrics.time_to_engage(read_table(s, d, "events")), 3), "WITH n AS (SELECT user_id, event_type, ts, first_value(CASE WHEN event_type = 'login' THEN ts END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS nxt FROM events) SELECT user_id, count(*) AS incidents, round(avg((epoch_us(nxt) - epoch_us(ts)) / 1e6), 3) AS mean_seconds FROM n WHERE event_type = 'error' AND nxt IS NOT NULL GROUP BY user_id")

# --- service and streams
add("extract_json", lambda s, d: service.extract_json(mined(s, d).seeds), chain("""SELECT report_id, '[' || string_agg('{"entity":"' || entity || '","value":"' || value || '"}', ',' ORDER BY sent_no, entity, value) || ']' AS entities FROM seeds GROUP BY report_id"""))
add("extract_by_id", lambda s, d: service.by_id(corpus.order_reports(s, d), mined(s, d).types, 25), chain("""SELECT report_id, '[' || string_agg('{"entity":"' || entity || '","value":"' || value || '"}', ',' ORDER BY sent_no, entity, value) || ']' AS entities FROM seeds WHERE report_id = 25 GROUP BY report_id"""))
add("extract_json_model", lambda s, d: service.extract_json(service.extract_by_model(corpus.order_reports(s, d), fitted(s, d, "joint")[0])))
add("extract_by_id_model", lambda s, d: service.by_id(corpus.order_reports(s, d), None, 25, fitted(s, d, "joint")[0]))
add("stream_auto_trigger_model", lambda s, d: auto_trigger(s, d, model=fitted(s, d, "joint")[0]))
add("feed_required_entities", lambda s, d: service.feed(mined(s, d).mentions, ("customer name", "source ip")), chain("SELECT report_id, min(CASE WHEN entity = 'customer name' THEN value END) AS customer_name, min(CASE WHEN entity = 'source ip' THEN value END) AS source_ip FROM mentions WHERE entity IN ('customer name', 'source ip') GROUP BY report_id HAVING count(DISTINCT entity) = 2"))


def _udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    service.register(spark)
    return spark.sql("SELECT r.report_id, e.name, e.value FROM {r} r, LATERAL extract_entities(r.description) e", r=corpus.event_reports(spark, sf_dir).where("resolved"))


def _sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    service.register(spark)
    return spark.sql("SELECT o_orderkey, value_type(o_orderpriority) AS a, value_type(cast(o_orderkey AS STRING)) AS b, split_camel('orderPriority') AS c FROM {o}", o=read_table(spark, sf_dir, "orders"))


from reportgraph.functions.text import value_type_sql as _vt  # noqa: E402

add("extract_udtf", _udtf, "WITH l AS (SELECT event_id AS report_id, unnest(string_split(" + corpus.EVENT_TEXT + " || chr(10) || 'Batch Key: ' || json_extract_string(props, '$.k'), chr(10))) AS s FROM events WHERE event_type = 'error') SELECT report_id, split_part(s, ': ', 1) AS name, split_part(s, ': ', 2) AS value FROM l")
add("sql_functions", _sql_functions, f"SELECT o_orderkey, {_vt('o_orderpriority')} AS a, {_vt('o_orderkey::VARCHAR')} AS b, 'order Priority' AS c FROM orders")


def _sql_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    service.register(spark)
    return spark.sql("SELECT page_id, size(tokenize(url)) AS tokens, strip_markup(html) AS text, tag_json(concat('Page Url: ', url)) AS entities FROM {p}", p=read_table(spark, sf_dir, "pages"))


def _npmi_aggregate(spark: SparkSession, sf_dir: str) -> DataFrame:
    service.register(spark)
    return rounded(spark.sql("SELECT o_orderstatus, npmi_of(o_orderpriority = '1-URGENT', o_totalprice > 100000) AS npmi, npmi_of(o_orderkey % 2 = 0, o_orderkey % 4 = 0) AS nested FROM {o} GROUP BY o_orderstatus", o=read_table(spark, sf_dir, "orders")))


_BOTH = "CASE WHEN count(*) FILTER ({a}) = 0 OR count(*) FILTER ({b}) = 0 THEN NULL WHEN count(*) FILTER ({a} AND {b}) = 0 THEN -1 ELSE round(ln(count(*) FILTER ({a} AND {b}) * count(*)::DOUBLE / (count(*) FILTER ({a}) * count(*) FILTER ({b})::DOUBLE)) / -ln(count(*) FILTER ({a} AND {b}) / count(*)::DOUBLE), 6) END"
add("sql_functions_documents", _sql_documents, r"""SELECT page_id, len(regexp_extract_all(url, '[A-Za-z][A-Za-z0-9+.-]*://\S+'))::INTEGER AS tokens, trim(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script\b.*?</script\s*>|<style\b.*?</style\s*>|<!--.*?-->', ' ', 'g'), '<[^>]+>', ' ', 'g'), '\s+', ' ', 'g')) AS text, '[{"name":"Page Url","value":"' || url || '"}]' AS entities FROM pages""")
add("npmi_aggregate", _npmi_aggregate, "SELECT o_orderstatus, " + _BOTH.format(a="o_orderpriority = '1-URGENT'", b="o_totalprice > 100000") + " AS npmi, " + _BOTH.format(a="o_orderkey % 2 = 0", b="o_orderkey % 4 = 0") + " AS nested FROM orders GROUP BY o_orderstatus")
for _name, (_q, _sql) in STREAMS.items():
    add(_name, _q, _sql)
