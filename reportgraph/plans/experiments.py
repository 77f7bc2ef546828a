"""Ablations, costs and variants."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reportgraph.functions import markup
from reportgraph.functions.vectors import train_word2vec
from reportgraph.operators import labeling, relations
from reportgraph.plans.applications import routing_rows
from reportgraph.plans.mining import mined, rounded
from reportgraph.sources import corpus, datasource
from reportgraph.sources.io import read_table
from reportgraph.operators.triage import FEATURE_SETS

QUERIES: dict[str, tuple] = {}


def propagation_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mentions, related pairs and kept relations with and without propagated labels."""
    m = mined(spark, sf_dir)
    out = None
    for name, mentions in (("seeds only", m.mentions.join(m.propagated.select("report_id", "sent_no").distinct(), ["report_id", "sent_no"], "left_anti")), ("propagated", m.mentions)):
        r = relations.score(relations.with_frequencies(relations.pairs(mentions), relations.frequencies(mentions)))
        row = mentions.agg(F.count("*").alias("mentions"), F.countDistinct("entity").alias("entities")).crossJoin(r.agg(F.count("*").alias("pairs"), F.count(F.when(F.col("npmi") >= 0, 1)).alias("kept"))).withColumn("labels", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


def approximate_top_k(spark: SparkSession, sf_dir: str, k: int = 50) -> DataFrame:
    """The most frequent grams by a sketch of bounded size, with the exact counts of those found."""
    names = labeling.drop_noisy_names(mined(spark, sf_dir).candidates).select("name")
    grams = labeling.name_ngrams(names).select("gram")
    top = grams.selectExpr(f"explode(approx_top_k(gram, {k}, 10000)) AS t").select(F.col("t.item").alias("gram"), F.col("t.count").alias("estimate"))
    exact = grams.join(F.broadcast(top.select("gram")), "gram", "left_semi").groupBy("gram").agg(F.count("*").alias("freq"))
    return top.join(exact, "gram")


def feature_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows and inputs that differ from zero for each feature set."""
    from pyspark.ml.functions import vector_to_array

    out = None
    for fs in FEATURE_SETS:
        x = vector_to_array("features")
        row = routing_rows(spark, sf_dir, fs).agg(F.count("*").alias("rows"), F.avg(F.size(F.filter(x, lambda v: v != 0))).alias("inputs_a_row")).withColumn("features", F.lit(fs))
        out = row if out is None else out.unionByName(row)
    return rounded(out)


def parsed_markup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Table rows by the parser; the expressions give the same on tables that are not nested."""
    r = corpus.order_reports(spark, sf_dir)
    return r.select("report_id", F.inline(markup.parsed_rows(F.col("description"))))


def generated_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    datasource.register(spark)
    return spark.read.format("reports").option("rows", 1000).load()


def word_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trained vectors of the words of all documents: the number of words and the width."""
    from pyspark.ml.functions import vector_to_array

    from reportgraph.functions import text as T

    tokens = T.sentences(read_table(spark, sf_dir, "documents"), "text", "doc_id", clean=False).select(F.split("text", " ").alias("tokens"))
    v = train_word2vec(tokens, dim=32, min_count=5).getVectors()
    return v.select("word", F.size(vector_to_array("vector")).alias("width"))


from reportgraph.plans.oracles import chain  # noqa: E402

_ABLATION = "SELECT {label} AS labels, (SELECT count(*) FROM {m}) AS mentions, (SELECT count(DISTINCT entity) FROM {m}) AS entities, (SELECT count(*) FROM {p}) AS pairs, (SELECT count(*) FROM {p} WHERE npmi >= 0) AS kept"
_SEED_PAIRS = """own AS (SELECT * FROM seeds s WHERE NOT EXISTS (SELECT 1 FROM propagated p WHERE p.report_id = s.report_id AND p.sent_no = s.sent_no)), own_f AS (SELECT entity, count(*) AS f FROM own GROUP BY entity), own_d AS (SELECT DISTINCT report_id, sent_no, entity FROM own),
 own_p AS (SELECT a.entity AS e1, b.entity AS e2, count(*) AS j FROM own_d a JOIN own_d b ON a.report_id = b.report_id AND a.sent_no = b.sent_no AND a.entity < b.entity GROUP BY ALL),
 own_s AS (SELECT e1, e2, ln(j * t::DOUBLE / (x.f::DOUBLE * y.f)) / -ln(j / t::DOUBLE) AS npmi FROM own_p JOIN own_f x ON e1 = x.entity JOIN own_f y ON e2 = y.entity, (SELECT sum(f) AS t FROM own_f))"""
QUERIES["ablation_propagation"] = (propagation_ablation, chain(_ABLATION.format(label="'seeds only'", m="own", p="own_s") + " UNION ALL " + _ABLATION.format(label="'propagated'", m="mentions", p="scored"), _SEED_PAIRS))
QUERIES["approx_top_k_types"] = (approximate_top_k, None)
QUERIES["cost_features"] = (feature_cost, None)
QUERIES["clean_parsed_rows"] = (parsed_markup, chain("SELECT report_id, name, value FROM candidates WHERE pattern = 'table'"))
QUERIES["source_reports"] = (generated_reports, "SELECT k AS report_id, 'Label printer offline near dock ' || (k % 5) AS title, 'Dock Number: ' || (k % 5) || chr(10) || 'Source Ip: 10.0.' || (k % 256) || '.' || (k % 7) || chr(10) || 'printer at 10.0.' || (k % 256) || '.' || (k % 7) || ' is silent' AS description FROM range(0, 1000) t(k)")
QUERIES["word_vectors"] = (word_vectors, None)
