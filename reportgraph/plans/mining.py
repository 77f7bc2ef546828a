"""The mining chain end to end, and a query for each of its steps."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reportgraph.functions import text as T
from reportgraph.operators import graph, labeling, metrics, patterns, propagate, relations
from reportgraph.plans.oracles import STEPS, chain
from reportgraph.sources import corpus
from reportgraph.sources.io import checkpointed, read_table, stored

K = 100


@dataclass
class Mined:
    """What several methods read; each is written once to the shared folder."""

    sentences: DataFrame
    candidates: DataFrame
    types: DataFrame
    seeds: DataFrame
    value_types: DataFrame
    dictionary: DataFrame
    propagated: DataFrame
    mentions: DataFrame
    relations: DataFrame
    edges: DataFrame


def mine(reports: DataFrame, k: int = K, scope: str = "sentence", propagation: bool = True, names: tuple[str, ...] = ("key_value", "table"), text_col: str = "description") -> Mined:
    """From reports to the type graph: clean, bootstrap, type, propagate, relate."""
    sentences = stored(T.sentences(reports, text_col))
    candidates = stored(patterns.extract_all(sentences, names))
    types = checkpointed(labeling.top_k_types(candidates, k))
    seeds = stored(labeling.tag_patterns(candidates, types))
    value_types = checkpointed(labeling.entity_value_types(seeds))
    dictionary = stored(propagate.value_dictionary(seeds, value_types))
    propagated = stored(propagate.propagate(sentences, dictionary, seeds))
    cols = ["report_id", "sent_no", "entity", "value"]
    mentions = seeds.select(cols).unionByName(propagated.select(cols)) if propagation else seeds.select(cols)
    scored = relations.score(relations.score(relations.with_frequencies(relations.pairs(mentions, scope), relations.frequencies(mentions)), "pmi"))
    scored = checkpointed(scored.select("e1", "e2", "f_joint", "f1", "f2", "total", "pmi", "npmi"))
    return Mined(sentences, candidates, types, seeds, value_types, dictionary, propagated, mentions, scored, graph.type_graph(relations.keep(scored)))


_MINED: dict[tuple, Mined] = {}


def state_of(spark: SparkSession, sf_dir: str) -> tuple:
    """Time, size and number of files of the tables that reports are made of, by which a kept result is known to be of these data."""
    out = []
    for name in ("orders", "customer", "pages", "benchmark"):
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{name}.parquet")
        fs = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        content = fs.getContentSummary(path)
        out.append((fs.getFileStatus(path).getModificationTime(), content.getLength(), content.getFileCount()))
    return tuple(out)


def mined(spark: SparkSession, sf_dir: str) -> Mined:
    """The chain over the order reports of a folder, kept for the session."""
    key = (spark.sparkContext.applicationId, sf_dir, state_of(spark, sf_dir))
    if key not in _MINED:
        _MINED.clear()
        _MINED[key] = mine(corpus.order_reports(spark, sf_dir))
    return _MINED[key]


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def _step(field: str, *cols: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = getattr(mined(spark, sf_dir), field)
        return rounded(df.select(*cols) if cols else df)

    return query


def _rounded_sql(cols: str, source: str) -> str:
    return chain(f"SELECT {cols} FROM {source}")


#: name: (query, SQL or None)
QUERIES: dict[str, tuple] = {}


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = (query, sql)


R6 = "round({0}, 6) AS {0}"
add("order_reports", corpus.order_reports, f"WITH {corpus.REPORTS_SQL} SELECT * FROM reports")
add("order_reports_gold", corpus.order_reports_gold, f"WITH {corpus.GOLD_SQL} SELECT * FROM gold")
add("event_reports", corpus.event_reports, f"SELECT event_id AS report_id, 'Event of user ' || user_id AS title, {corpus.EVENT_TEXT} || chr(10) || 'Batch Key: ' || json_extract_string(props, '$.k') AS description, ts AS modified_at, event_type AS team, event_type = 'error' AS resolved FROM events")
add("dialogs", corpus.dialogs, "SELECT conv_id AS report_id, count(*) AS turns, string_agg(role || ' said' || chr(10) || text, chr(10) ORDER BY turn, role, text) AS description FROM conversations GROUP BY conv_id")
add("report_word_stats", lambda s, d: rounded(T.sentences(read_table(s, d, "documents"), "text", "doc_id", clean=False).select("report_id", F.size(F.split("text", " ")).alias("w")).groupBy("report_id").agg(F.sum("w").alias("w"), F.count("*").alias("n")).agg(F.avg("w").alias("mean_words"), F.avg("n").alias("mean_sentences"), F.count("*").alias("reports"))),
    "WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS s FROM documents), t AS (SELECT doc_id, trim(regexp_replace(s, ' +', ' ', 'g')) AS s FROM l), g AS (SELECT doc_id, sum(len(string_split(s, ' '))) AS w, count(*) AS n FROM t WHERE s <> '' GROUP BY doc_id) SELECT round(avg(w), 6) AS mean_words, round(avg(n), 6) AS mean_sentences, count(*) AS reports FROM g")

add("clean_wide_tables", lambda s, d: corpus.order_reports(s, d).select("report_id", T.drop_wide_tables(F.col("description")).alias("text")),
    f"WITH {corpus.REPORTS_SQL} SELECT report_id, replace(description, '{corpus.WIDE_TABLE}', '') AS text FROM reports")
add("clean_two_column_rows", lambda s, d: corpus.order_reports(s, d).select("report_id", F.inline(T.two_column_rows(F.col("description")))),
    chain("SELECT report_id, name, value FROM candidates WHERE pattern = 'table'"))
add("clean_strip_markup", lambda s, d: read_table(s, d, "pages").select("page_id", T.squeeze(T.strip_markup(F.col("html"))).alias("text")),
    r"""WITH a AS (SELECT page_id, regexp_replace(html, '(?is)<script\b.*?</script\s*>|<style\b.*?</style\s*>|<!--.*?-->', ' ', 'g') AS t FROM pages),
 b AS (SELECT page_id, regexp_replace(t, '(?i)</?(?:p|div|br|li|ul|ol|h[1-6]|tr|table|nav|article|section|footer|header|title|body|head|html)\b[^>]*>', chr(10), 'g') AS t FROM a),
 c AS (SELECT page_id, regexp_replace(t, '<[^>]+>', '', 'g') AS t FROM b)
 SELECT page_id, trim(regexp_replace(replace(replace(replace(replace(replace(replace(replace(replace(t, '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&middot;', '·'), '&copy;', '©'), '&amp;', '&'), '\s+', ' ', 'g')) AS text FROM c""")
add("clean_sentences", _step("sentences"), chain("SELECT * FROM sentences"))
add("clean_squeeze", lambda s, d: read_table(s, d, "documents").select("doc_id", T.squeeze(F.col("text")).alias("text")), r"SELECT doc_id, trim(regexp_replace(text, '\s+', ' ', 'g')) AS text FROM documents")
add("clean_tokens", lambda s, d: read_table(s, d, "documents").select("doc_id", F.size(F.regexp_extract_all("text", F.lit(r"[\p{L}]+|[0-9]+"), F.lit(0))).alias("tokens")), r"SELECT doc_id, len(regexp_extract_all(text, '[\p{L}]+|[0-9]+')) AS tokens FROM documents")
add("clean_camel_tokens", lambda s, d: corpus.order_reports(s, d).select("report_id", F.array_join(T.tokenize(F.concat("title", F.lit(" HTTPServer orderPriority "), "description")), "|").alias("tokens")),
    f"WITH {corpus.REPORTS_SQL}, t AS (SELECT report_id, regexp_extract_all(title || ' HTTPServer orderPriority ' || description, '{T.TOKEN}') AS t FROM reports) "
    r"SELECT report_id, array_to_string(flatten(list_transform(t, lambda x: CASE WHEN regexp_full_match(x, '\p{L}+') THEN string_split(regexp_replace(regexp_replace(x, '(\p{Ll})(\p{Lu})', '\1 \2', 'g'), '(\p{Lu})(\p{Lu}\p{Ll})', '\1 \2', 'g'), ' ') ELSE [x] END)), '|') AS tokens FROM t")
add("clean_windows", lambda s, d: T.windows(read_table(s, d, "documents").select("doc_id", F.split("text", " ").alias("tokens"))).select("doc_id", "window", F.size("tokens").alias("size")),
    "WITH t AS (SELECT doc_id, len(string_split(text, ' ')) AS n FROM documents), w AS (SELECT doc_id, n, unnest(range(0, CASE WHEN n <= 300 THEN 1 ELSE ceil((n - 300) / 250.0)::BIGINT + 1 END)) AS w FROM t) SELECT doc_id, w::INTEGER AS \"window\", least(300, n - w * 250)::INTEGER AS size FROM w")

add("kv_candidates", lambda s, d: mined(s, d).candidates.where("pattern = 'key_value'"), chain("SELECT * FROM candidates WHERE pattern = 'key_value'"))
add("table_candidates", lambda s, d: mined(s, d).candidates.where("pattern = 'table'"), chain("SELECT * FROM candidates WHERE pattern = 'table'"))
add("equals_candidates", lambda s, d: patterns.extract_all(T.sentences(read_table(s, d, "documents"), "text", "doc_id", clean=False), ("equals",)).where(F.col("value").startswith('"')).select("report_id", "value"),
    "WITH l AS (SELECT doc_id, trim(regexp_replace(unnest(string_split(text, chr(10))), ' +', ' ', 'g')) AS s FROM documents), e AS (SELECT doc_id, trim(substr(s, 1, position('=' IN s) - 1)) AS name, trim(substr(s, position('=' IN s) + 1)) AS value FROM l WHERE contains(s, '=')) SELECT doc_id AS report_id, value FROM e WHERE name <> '' AND value LIKE '\"%' AND len(string_split(name, ' ')) <= 6")
add("email_candidates", lambda s, d: patterns.extract_all(T.sentences(read_table(s, d, "documents"), "text", "doc_id", clean=False), ("email",)).select("report_id", "value"),
    r"WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS s FROM documents) SELECT doc_id AS report_id, unnest(regexp_extract_all(s, '[0-9A-Za-z_.+-]+@[0-9A-Za-z_-]+(?:\.[0-9A-Za-z_-]+)+')) AS value FROM l")
add("secret_candidates", lambda s, d: patterns.extract_all(T.sentences(read_table(s, d, "documents"), "text", "doc_id", clean=False), ("secret",)).select("report_id", "value"),
    r"WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS s FROM documents) SELECT doc_id AS report_id, unnest(regexp_extract_all(s, '\b[0-9a-f]{40}\b')) AS value FROM l")
add("noisy_names_dropped", lambda s, d: labeling.drop_noisy_names(mined(s, d).candidates).groupBy("name").agg(F.count("*").alias("c")), chain("SELECT name, c FROM names"))
add("name_ngrams", lambda s, d: labeling.name_ngrams(labeling.drop_noisy_names(mined(s, d).candidates).select("name").distinct()).select("name", "gram", "n", "place"), chain("SELECT name, gram, n::INTEGER AS n, place::INTEGER AS place FROM grams"))
add("gram_counts", lambda s, d: labeling.gram_counts(mined(s, d).candidates), chain("SELECT gram, n::INTEGER AS n, freq FROM counts"))
add("top_k_types", _step("types"), chain("SELECT gram, n::INTEGER AS n, freq, rank::INTEGER AS rank FROM types"))
add("resolved_names", lambda s, d: labeling.resolve_names(mined(s, d).candidates, mined(s, d).types), chain("SELECT name, entity FROM resolved"))
add("tagged_mentions", _step("seeds"), chain("SELECT * FROM seeds"))
add("value_types", lambda s, d: mined(s, d).candidates.select("value").distinct().select("value", T.value_type(F.col("value")).alias("value_type")), chain(f"SELECT DISTINCT value, {T.value_type_sql('value')} AS value_type FROM candidates"))
_CELLS = ("o_orderpriority", "o_orderstatus", "cast(o_orderkey as string)", "cast(cast(o_totalprice as decimal(18,2)) as string)")
add("value_types_by_table", lambda s, d: read_table(s, d, "orders").select(F.expr("stack(4, " + ", ".join(f"'{k}', {c}" for k, c in enumerate(_CELLS)) + ") as (col, value)")).groupBy("col", T.value_type(F.col("value")).alias("value_type")).agg(F.count("*").alias("c")),
    " UNION ALL ".join(f"SELECT '{k}' AS col, {T.value_type_sql(c)} AS value_type, count(*) AS c FROM orders GROUP BY ALL" for k, c in enumerate(_CELLS)))
add("entity_value_type_majority", _step("value_types"), chain("SELECT * FROM vtypes"))
add("value_dictionary", _step("dictionary"), chain("SELECT value, tokens::INTEGER AS tokens, entity, support FROM dictionary"))
add("propagated_mentions", _step("propagated"), chain('SELECT report_id, sent_no, "begin"::INTEGER AS "begin", size::INTEGER AS size, entity, value FROM propagated'))


def _recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of the gold mentions found, by place; prose is reached by propagation alone."""
    gold = corpus.order_reports_gold(spark, sf_dir).groupBy("report_id", "place", "entity", "value").agg(F.count("*").alias("g"))
    found = mined(spark, sf_dir).mentions.groupBy("report_id", "entity", "value").agg(F.count("*").alias("f"))
    rows = gold.join(found, ["report_id", "entity", "value"], "left")
    return rounded(rows.groupBy("place").agg(F.sum("g").alias("gold"), F.sum(F.when(F.col("f").isNotNull(), F.col("g")).otherwise(0)).alias("found"))
                   .withColumn("recall", F.col("found") / F.col("gold")))


add("propagation_recall", _recall, chain("""SELECT place, sum(g)::BIGINT AS gold, sum(CASE WHEN f IS NULL THEN 0 ELSE g END)::BIGINT AS found, round(sum(CASE WHEN f IS NULL THEN 0 ELSE g END) / sum(g), 6) AS recall
 FROM (SELECT report_id, place, entity, value, count(*) AS g FROM gold GROUP BY ALL) LEFT JOIN (SELECT report_id, entity, value, count(*) AS f FROM mentions GROUP BY ALL) USING (report_id, entity, value) GROUP BY place""", corpus.GOLD_SQL.split(" AS (", 1)[0] and "gold AS" + corpus.GOLD_SQL.split(", gold AS", 1)[1]))
add("temporal_split", lambda s, d: labeling.temporal_split(read_table(s, d, "orders"), "o_orderdate").groupBy("part").agg(F.count("*").alias("rows"), F.min("o_orderdate").alias("first"), F.max("o_orderdate").alias("last")),
    "WITH e AS (SELECT quantile_disc(o_orderdate, 0.8) AS edge FROM orders) SELECT CASE WHEN o_orderdate > edge THEN 'test' ELSE 'train' END AS part, count(*) AS rows, min(o_orderdate) AS first, max(o_orderdate) AS last FROM orders, e GROUP BY 1")

add("entity_frequencies", lambda s, d: relations.frequencies(mined(s, d).mentions), chain("SELECT * FROM freqs"))
add("entity_pairs", lambda s, d: relations.pairs(mined(s, d).mentions), chain("SELECT * FROM joint"))
add("entity_pairs_by_report", lambda s, d: relations.pairs(mined(s, d).mentions, "report"),
    chain("SELECT a.entity AS e1, b.entity AS e2, count(*) AS f_joint FROM (SELECT DISTINCT report_id, entity FROM mentions) a JOIN (SELECT DISTINCT report_id, entity FROM mentions) b ON a.report_id = b.report_id AND a.entity < b.entity GROUP BY ALL"))
add("pair_pmi", _step("relations", "e1", "e2", "pmi"), chain("SELECT e1, e2, round(pmi, 6) AS pmi FROM scored"))
add("pair_npmi", _step("relations", "e1", "e2", "f1", "f2", "f_joint", "npmi"), chain("SELECT e1, e2, f1, f2, f_joint, round(npmi, 6) AS npmi FROM scored"))
_T = "total::DOUBLE"
_CELL = "CASE WHEN {j} > 0 AND {a} > 0 AND {b} > 0 THEN {j} / {t} * ln({j} * {t} / ({a} * {b})) ELSE 0 END"
_MI = " + ".join(_CELL.format(j=f"(({j})::DOUBLE)", a=f"(({a})::DOUBLE)", b=f"(({b})::DOUBLE)", t=_T) for j, a, b in (("f_joint", "f1", "f2"), ("f1 - f_joint", "f1", "total - f2"), ("f2 - f_joint", "total - f1", "f2"), ("total - f1 - f2 + f_joint", "total - f1", "total - f2")))
add("pair_mi", lambda s, d: rounded(relations.score(mined(s, d).relations, "mi").select("e1", "e2", "mi")), chain(f"SELECT e1, e2, round({_MI}, 6) AS mi FROM scored"))
add("relations_kept", lambda s, d: rounded(relations.keep(mined(s, d).relations).select("e1", "e2", "npmi")), chain("SELECT e1, e2, round(npmi, 6) AS npmi FROM scored WHERE npmi >= 0"))
add("relations_kept_in_integers", lambda s, d: relations.independent_or_better(mined(s, d).relations).select("e1", "e2"), chain("SELECT e1, e2 FROM scored WHERE npmi >= 0"))
#: Published counts and scores of six pairs; the total that fits them is ours.
NPMI_ROWS = ((564, 558, 557, 0.99), (761, 654, 486, 0.88), (860, 985, 432, 0.78), (1071, 985, 124, 0.47), (761, 72908, 1, -0.38), (72908, 19125, 11, -0.55))
NPMI_TOTAL = 390_000
add("npmi_golden", lambda s, d: rounded(relations.score(s.createDataFrame([(a, b, c, NPMI_TOTAL, p) for a, b, c, p in NPMI_ROWS], "f1 long, f2 long, f_joint long, total long, printed double")).select("f1", "f2", "f_joint", "printed", "npmi")),
    "SELECT f1::BIGINT AS f1, f2::BIGINT AS f2, j::BIGINT AS f_joint, p::DOUBLE AS printed, round(ln(j * 390000.0::DOUBLE / (f1::DOUBLE * f2)) / -ln(j / 390000.0::DOUBLE), 6) AS npmi FROM (VALUES " + ", ".join(map(str, NPMI_ROWS)) + ") AS v(f1, f2, j, p)")

add("type_graph_edges", _step("edges"), chain("SELECT src, dst, round(weight, 6) AS weight FROM edges"))


def _full_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = mined(spark, sf_dir)
    nodes, edges = graph.full_graph(corpus.order_reports(spark, sf_dir), m.mentions, relations.keep(m.relations))
    count = lambda df, what: df.groupBy("kind").agg(F.count("*").alias("n")).withColumn("what", F.lit(what))
    return count(nodes, "node").unionByName(count(edges, "edge"))


add("full_graph_counts", _full_graph, chain("""SELECT 'report' AS kind, count(*) AS n, 'node' AS what FROM base UNION ALL SELECT 'team', count(DISTINCT r_name || c_mktsegment), 'node' FROM base
 UNION ALL SELECT 'type', count(DISTINCT entity), 'node' FROM mentions UNION ALL SELECT 'value', count(*), 'node' FROM (SELECT DISTINCT entity, value FROM mentions) UNION ALL SELECT 'mentions', count(*), 'edge' FROM (SELECT DISTINCT report_id, entity, value FROM mentions)
 UNION ALL SELECT 'handled by', count(*), 'edge' FROM base UNION ALL SELECT 'is a', count(*), 'edge' FROM (SELECT DISTINCT entity, value FROM mentions) UNION ALL SELECT 'related', count(*), 'edge' FROM edges"""))
add("shared_values", lambda s, d: graph.shared_values(mined(s, d).mentions), chain("SELECT entity, value, count(DISTINCT report_id) AS reports, min(report_id) AS first_report FROM mentions GROUP BY entity, value HAVING count(DISTINCT report_id) >= 2"))
add("graph_neighbors", lambda s, d: rounded(graph.neighbors(mined(s, d).edges, "customer name")), chain("SELECT dst AS node, round(weight, 6) AS weight FROM two_way WHERE src = 'customer name'"))
add("node_degrees", lambda s, d: rounded(graph.degrees(mined(s, d).edges)), chain("SELECT src AS node, count(*) AS degree, round(sum(weight), 6) AS weighted_degree FROM two_way GROUP BY src"))
add("components", lambda s, d: graph.components(mined(s, d).edges), chain("SELECT node, min(other) AS component FROM reach GROUP BY node", "reach AS (SELECT src AS node, src AS other FROM two_way UNION SELECT r.node, b.dst FROM reach r JOIN two_way b ON r.other = b.src)"))
add("triangles", lambda s, d: graph.triangles(mined(s, d).edges), chain("SELECT x.src AS a, x.dst AS b, y.dst AS c FROM edges x JOIN edges y ON x.dst = y.src JOIN edges z ON z.src = x.src AND z.dst = y.dst"))
#: Nine edges of the published sketch of a type graph (lines 287 to 306), names written out; the weights are ours.
SKETCH = (("network id", "gateway id"), ("network id", "network region"), ("network id", "network name"), ("network id", "subscription id"), ("network name", "network region"), ("gateway id", "tunnel name"), ("encap type", "tunnel name"), ("gateway id", "network name"), ("network name", "subscription id"))


def sketch(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(min(e), max(e), round(0.9 - 0.05 * k, 2)) for k, e in enumerate(SKETCH)], "src string, dst string, weight double")


def _cliques(edges: DataFrame) -> DataFrame:
    return rounded(graph.maximal_cliques(edges).withColumn("members", F.array_join("members", "|")))


#: Cliques grown by larger neighbours of all members; maximal are those that no node is a neighbour of.
_CLIQUES = """adj AS (SELECT src, list(dst) AS near FROM two_way GROUP BY src), grown AS (SELECT [src] AS c FROM adj UNION ALL SELECT list_append(c, src) FROM grown JOIN adj ON src > c[-1] AND len(list_intersect(near, c)) = len(c)),
 whole AS (SELECT c FROM grown WHERE len(c) > 1 AND NOT EXISTS (SELECT 1 FROM adj WHERE len(list_intersect(near, c)) = len(c)))"""
_CLIQUE_ROWS = "SELECT array_to_string(c, '|') AS members, len(c)::INTEGER AS size, round(min(weight), 6) AS min_weight, round(avg(weight), 6) AS mean_weight FROM whole JOIN edges ON list_contains(c, src) AND list_contains(c, dst) GROUP BY c"
add("maximal_cliques", lambda s, d: _cliques(mined(s, d).edges), chain(_CLIQUE_ROWS, _CLIQUES))
_SKETCH_ROWS = ", ".join(f"('{min(e)}', '{max(e)}', {round(0.9 - 0.05 * k, 2)}::DOUBLE)" for k, e in enumerate(SKETCH))
add("maximal_cliques_sketch", lambda s, d: _cliques(sketch(s)), f"WITH RECURSIVE edges AS (SELECT * FROM (VALUES {_SKETCH_ROWS}) v(src, dst, weight)), two_way AS (SELECT src, dst FROM edges UNION ALL SELECT dst, src FROM edges), {_CLIQUES} {_CLIQUE_ROWS}")


def _graph_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often a report of each team mentions a value of each type."""
    m = mined(spark, sf_dir)
    _, edges = graph.full_graph(corpus.order_reports(spark, sf_dir), m.mentions, relations.keep(m.relations))
    found = graph.match(edges, [("report", "mentions", "value"), ("value", "is a", "type"), ("report", "handled by", "team")])
    return found.groupBy("type", "team").agg(F.count("*").alias("n"))


add("graph_match", _graph_match, chain("SELECT 'type:' || entity AS type, 'team:' || r_name || '/' || c_mktsegment AS team, count(*) AS n FROM (SELECT DISTINCT report_id, entity, value FROM mentions) m JOIN base ON k = report_id GROUP BY ALL"))
_BFS = """walk AS (SELECT 'customer name' AS target, 0 AS hops, ['customer name'] AS path UNION ALL SELECT b.dst, hops + 1, list_append(path, b.dst) FROM walk w JOIN two_way b ON w.target = b.src WHERE NOT list_contains(path, b.dst))"""
add("hop_paths", lambda s, d: graph.shortest_paths(mined(s, d).edges, s.createDataFrame([("customer name",)], "source string")).select("target", "hops"), chain("SELECT target, min(hops)::INTEGER AS hops FROM walk GROUP BY target", _BFS))
_WALK = """walk AS (SELECT 'customer name' AS target, 0.0::DOUBLE AS dist, ['customer name'] AS path UNION ALL SELECT b.dst, dist + 1 - weight, list_append(path, b.dst) FROM walk w JOIN two_way b ON w.target = b.src WHERE NOT list_contains(path, b.dst))"""
add("weighted_paths", lambda s, d: rounded(graph.shortest_paths(mined(s, d).edges, s.createDataFrame([("customer name",)], "source string"), "distance").select("target", F.aggregate("weights", F.lit(0.0), lambda a, x: a + 1 - x).alias("distance"))), chain("SELECT target, round(min(dist), 6) AS distance FROM walk GROUP BY target", _WALK))


def _entity_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Precision at rank of the types by frequency; a type is valid if the rendered reports have a field of that name."""
    valid = [e for x in corpus.LINES for e, _ in x.gold]
    top = labeling.top_k_types(mined(spark, sf_dir).candidates, K, subsume=False)
    return rounded(metrics.precision_at(top.select("rank", F.col("gram").isin(*sorted(set(valid))).alias("is_valid")), metrics.TYPE_RANKS))


_VALID = ", ".join(f"'{e}'" for e in sorted({e for x in corpus.LINES for e, _ in x.gold}))
add("precision_at_n_types", _entity_precision, chain(f"SELECT n::INTEGER AS n, sum(v)::BIGINT AS hits, round(sum(v) / n, 6) AS precision FROM (SELECT row_number() OVER (ORDER BY freq DESC, n DESC, gram) AS r, gram IN ({_VALID}) AS v FROM top) JOIN (SELECT unnest([1, 5, 10, 20, 35, 50, 75, 100]) AS n) ON r <= n WHERE n <= (SELECT count(*) FROM top) GROUP BY n"))
#: Pairs that the rendering puts on one line.
TRUE_PAIRS = tuple(sorted({tuple(sorted((a, b))) for x in corpus.LINES if x.place == "prose" for i, (a, _) in enumerate(x.gold) for b, _ in x.gold[i + 1 :]}))


def _pair_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = mined(spark, sf_dir).relations
    good = F.concat_ws("|", "e1", "e2").isin(*["|".join(p) for p in TRUE_PAIRS])
    from pyspark.sql import Window

    ranked = r.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("f_joint"), "e1", "e2"))).select("rank", good.alias("is_valid"))
    return rounded(metrics.precision_at(ranked, metrics.PAIR_RANKS))


add("precision_at_n_pairs", _pair_precision, chain("SELECT n::INTEGER AS n, sum(v)::BIGINT AS hits, round(sum(v) / n, 6) AS precision FROM (SELECT row_number() OVER (ORDER BY f_joint DESC, e1, e2) AS r, e1 || '|' || e2 IN (" + ", ".join(f"'{a}|{b}'" for a, b in TRUE_PAIRS) + ") AS v FROM scored) JOIN (SELECT unnest([" + ", ".join(map(str, metrics.PAIR_RANKS)) + "]) AS n) ON r <= n WHERE n <= (SELECT count(*) FROM scored) GROUP BY n"))


def _k_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many types, and mentions in the patterns, each cut K leaves."""
    c = mined(spark, sf_dir).candidates
    out = None
    for k in (10, 25, 50, 100, 200):
        t = labeling.top_k_types(c, k)
        row = labeling.tag_patterns(c, t).agg(F.countDistinct("entity").alias("entities"), F.count("*").alias("mentions")).withColumn("k", F.lit(k))
        out = row if out is None else out.unionByName(row)
    return out


add("k_sweep", _k_sweep, " UNION ALL ".join("SELECT * FROM (" + chain(f"SELECT count(DISTINCT entity) AS entities, count(*) AS mentions, {k}::INTEGER AS k FROM seeds").replace("LIMIT 100", f"LIMIT {k}") + ")" for k in (10, 25, 50, 100, 200)))


def _fixed_errors(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Seed mentions with their places, and the same with fixed mistakes: one in seven is missing, one in eleven has another type."""
    m = mined(spark, sf_dir)
    gold = propagate.seed_places(m.seeds, m.sentences)
    k = F.col("report_id")
    return gold, gold.where(k % 7 != 0).withColumn("entity", F.when(k % 11 == 0, "wrong").otherwise(F.col("entity")))


_PLACES = "places AS (SELECT d.report_id, d.sent_no, entity, (len(string_split(replace(text, chr(9), ' '), ' ')) - len(string_split(value, ' ')))::INTEGER AS b, len(string_split(value, ' '))::INTEGER AS size FROM seeds d JOIN sentences s ON s.report_id = d.report_id AND s.sent_no = d.sent_no), bad AS (SELECT report_id, sent_no, CASE WHEN report_id % 11 = 0 THEN 'wrong' ELSE entity END AS entity, b, size FROM places WHERE report_id % 7 <> 0)"
add("error_examples_fixed", lambda s, d: metrics.error_examples(*_fixed_errors(s, d)), chain("""SELECT report_id, sent_no::INTEGER AS sent_no, b AS "begin", gold, pred, CASE WHEN pred IS NULL THEN 'false negative' ELSE 'confused' END AS kind FROM (SELECT p.report_id, p.sent_no, p.b, p.entity AS gold, q.entity AS pred FROM places p LEFT JOIN bad q ON p.report_id = q.report_id AND p.sent_no = q.sent_no AND p.b = q.b)
 WHERE pred IS DISTINCT FROM gold ORDER BY report_id, sent_no, b LIMIT 50""", _PLACES))
add("span_prf_fixed", lambda s, d: rounded(metrics.span_prf(*_fixed_errors(s, d))), chain("""SELECT gold, pred, tp, round(tp / pred, 6) AS precision, round(tp / gold, 6) AS recall, round(2 * (tp / pred) * (tp / gold) / (tp / pred + tp / gold), 6) AS f1
 FROM (SELECT (SELECT count(*) FROM places) AS gold, (SELECT count(*) FROM bad) AS pred, (SELECT count(*) FROM bad WHERE entity <> 'wrong') AS tp)""", _PLACES))
assert set(STEPS) >= {"types", "mentions"}
