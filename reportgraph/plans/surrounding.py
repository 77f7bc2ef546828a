"""The general operators a user of the methods needs, one query each with its SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reportgraph.functions.vectors import cosine, dot, euclidean, norm
from reportgraph.sources.io import read_table, shared_dir

QUERIES: dict[str, tuple] = {}


def add(name: str, query, sql: str | None = None) -> None:
    """``query`` gets a reader of tables by name."""
    QUERIES[name] = (lambda spark, sf_dir: query(lambda t: read_table(spark, sf_dir, t)), sql)


r2 = lambda c, a, n=2: F.round(c, n).alias(a)

# --- projection and predicates
add("op_select", lambda t: t("orders").select("o_orderkey", r2(F.col("o_totalprice") * 1.1, "gross", 4)), "SELECT o_orderkey, round(o_totalprice * 1.1, 4) AS gross FROM orders")
add("op_filter", lambda t: t("orders").where(F.col("o_totalprice").between(1000, 50000) & F.col("o_orderpriority").isin("1-URGENT", "2-HIGH")).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000 AND o_orderpriority IN ('1-URGENT', '2-HIGH')")
add("op_case", lambda t: t("orders").select("o_orderkey", F.when(F.col("o_totalprice") > 200000, "large").when(F.col("o_totalprice") > 50000, "middle").otherwise("small").alias("size")), "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'large' WHEN o_totalprice > 50000 THEN 'middle' ELSE 'small' END AS size FROM orders")
add("op_rlike", lambda t: t("documents").where(F.col("text").rlike(r"[0-9]{1,3}(\.[0-9]{1,3}){3}")).select("doc_id"), r"SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{1,3}(\.[0-9]{1,3}){3}')")
add("op_null_safe", lambda t: t("customer").join(t("orders").select(F.col("o_custkey").alias("k")).distinct(), F.col("c_custkey") == F.col("k"), "left").where(F.col("k").eqNullSafe(F.lit(None))).select("c_custkey"), "SELECT c_custkey FROM customer LEFT JOIN (SELECT DISTINCT o_custkey AS k FROM orders) ON c_custkey = k WHERE k IS NOT DISTINCT FROM NULL")
# --- joins
add("join_broadcast", lambda t: t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name"), "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
add("join_sort_merge", lambda t: t("lineitem").hint("merge").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
add("join_shuffled_hash", lambda t: t("orders").join(t("customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
for kind, word in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    add(f"join_{kind}", lambda t, kind=kind: t("customer").where("c_acctbal > 5000").join(t("orders").where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), kind).select(F.coalesce("c_custkey", F.lit(-1)).alias("c_custkey"), F.coalesce("o_orderkey", F.lit(-1)).alias("o_orderkey")),
        f"SELECT coalesce(c_custkey, -1) AS c_custkey, coalesce(o_orderkey, -1) AS o_orderkey FROM (SELECT * FROM customer WHERE c_acctbal > 5000) {word} JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') ON c_custkey = o_custkey")
add("join_semi", lambda t: t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
add("join_anti", lambda t: t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
add("join_cross", lambda t: t("nation").crossJoin(t("region")).select("n_name", "r_name"), "SELECT n_name, r_name FROM nation, region")
_BANDS = [(0, 900.0, 1000.0), (1, 1000.0, 1200.0), (2, 1200.0, 3000.0)]


def _range_join(t):
    part = t("part")
    bands = part.sparkSession.createDataFrame(_BANDS, "band int, lo double, hi double")
    return part.join(F.broadcast(bands), (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


add("join_range", _range_join, "SELECT band, count(*) AS n FROM part JOIN (VALUES (0, 900, 1000), (1, 1000, 1200), (2, 1200, 3000)) b(band, lo, hi) ON p_retailprice >= lo AND p_retailprice < hi GROUP BY band")


def _as_of(t):
    """For each purchase the user's latest click before it: both in one window, no join."""
    e = t("events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("click_id", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", F.coalesce("click_id", F.lit(-1)).alias("click_id"))


add("join_as_of", _as_of, "SELECT event_id, coalesce(click_id, -1) AS click_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS click_id FROM events) WHERE event_type = 'purchase'")


def _interval_join(t):
    e = t("events")
    a = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("u"), F.col("ts").alias("t0"))
    b = e.where("event_type = 'login'").select(F.col("event_id").alias("login_id"), "user_id", "ts")
    return a.join(b, (F.col("u") == F.col("user_id")) & (F.col("ts") >= F.col("t0")) & (F.col("ts") < F.col("t0") + F.expr("interval 6 hours"))).select("error_id", "login_id")


add("join_interval", _interval_join, "SELECT a.event_id AS error_id, b.event_id AS login_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 6 HOURS WHERE a.event_type = 'error' AND b.event_type = 'login'")
add("join_nested_loop", lambda t: t("nation").select(F.col("n_name").alias("a")).join(F.broadcast(t("nation").select(F.col("n_name").alias("b"))), (F.col("a") < F.col("b")) & (F.levenshtein("a", "b") <= 1)), "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_name < b.n_name AND levenshtein(a.n_name, b.n_name) <= 1")


def _lateral(t):
    spark = t("nation").sparkSession
    return spark.sql("SELECT n_name, c_custkey FROM {n} n, LATERAL (SELECT c_custkey FROM {c} c WHERE c.c_nationkey = n.n_nationkey ORDER BY c_custkey LIMIT 2)", n=t("nation"), c=t("customer"))


add("join_lateral", _lateral, "SELECT n_name, c_custkey FROM nation n, LATERAL (SELECT c_custkey FROM customer c WHERE c.c_nationkey = n.n_nationkey ORDER BY c_custkey LIMIT 2)")
# --- aggregation
add("agg_hash", lambda t: t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(r2(F.sum("l_quantity"), "qty"), r2(F.avg("l_discount"), "disc", 6), F.count("*").alias("n")), "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, count(*) AS n FROM lineitem GROUP BY ALL")
add("agg_distinct", lambda t: t("lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")), "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
add("agg_percentile", lambda t: t("orders").groupBy("o_orderstatus").agg(r2(F.percentile("o_totalprice", 0.5), "median", 4), r2(F.percentile("o_totalprice", 0.9), "p90", 4)), "SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) AS median, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY 1")
add("agg_approx_distinct", lambda t: t("lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts")))
add("agg_approx_percentile", lambda t: t("orders").groupBy("o_orderstatus").agg(F.percentile_approx("o_totalprice", 0.5).alias("median")))
add("agg_grouping_sets", lambda t: t("customer").groupingSets([["c_nationkey"], ["c_mktsegment"], []], "c_nationkey", "c_mktsegment").agg(F.count("*").alias("n")).na.fill({"c_nationkey": -1, "c_mktsegment": "all"}), "SELECT coalesce(c_nationkey, -1) AS c_nationkey, coalesce(c_mktsegment, 'all') AS c_mktsegment, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_nationkey), (c_mktsegment), ())")
add("agg_cube", lambda t: t("lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
add("agg_rollup", lambda t: t("orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
add("agg_pivot", lambda t: t("orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).na.fill(0), "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS \"F\", count(*) FILTER (o_orderstatus = 'O') AS \"O\", count(*) FILTER (o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1")
add("agg_unpivot", lambda t: t("part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "measure", "value"), "SELECT p_partkey, 'size' AS measure, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
add("agg_collect_set", lambda t: t("orders").groupBy("o_orderpriority").agg(F.array_join(F.array_sort(F.collect_set("o_orderstatus")), ",").alias("states")), "SELECT o_orderpriority, string_agg(s, ',' ORDER BY s) AS states FROM (SELECT DISTINCT o_orderpriority, o_orderstatus AS s FROM orders) GROUP BY 1")
add("agg_max_by", lambda t: t("orders").groupBy("o_orderstatus").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest")), "SELECT o_orderstatus, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY 1")
add("agg_mode", lambda t: t("customer").groupBy("c_nationkey").agg(F.mode("c_mktsegment", deterministic=True).alias("segment")), "SELECT c_nationkey, arg_min(c_mktsegment, (-n, c_mktsegment)) AS segment FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY ALL) GROUP BY 1")
add("agg_listagg", lambda t: t("nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ";").alias("names")), "SELECT n_regionkey, string_agg(n_name, ';' ORDER BY n_name) AS names FROM nation GROUP BY 1")
add("agg_statistics", lambda t: t("lineitem").agg(r2(F.corr("l_quantity", "l_extendedprice"), "r", 6), r2(F.stddev("l_quantity"), "sd", 6), r2(F.variance("l_discount"), "var", 6)), "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r, round(stddev(l_quantity), 6) AS sd, round(var_samp(l_discount), 6) AS var FROM lineitem")
add("agg_hll_sketch", lambda t: t("lineitem").groupBy("l_returnflag").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts")))
add("agg_approx_top_k", lambda t: t("lineitem").selectExpr("approx_top_k(l_returnflag, 3) AS top"))
# --- windows
_W = lambda: Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
_SW = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"
for fn, col, sql in (
    ("row_number", F.row_number, "(row_number() {w})::INTEGER"), ("ntile", lambda: F.ntile(3), "(ntile(3) {w})::INTEGER"), ("percent_rank", F.percent_rank, "round(percent_rank() {w}, 6)"),
    ("lag", lambda: F.lag("o_totalprice"), "lag(o_totalprice) {w}"), ("lead", lambda: F.lead("o_totalprice"), "lead(o_totalprice) {w}"),
):
    add(f"window_{fn}", lambda t, fn=fn, col=col: t("orders").select("o_orderkey", (F.round(col().over(_W()), 6) if fn == "percent_rank" else col().over(_W())).alias("x")), f"SELECT o_orderkey, {sql.format(w=_SW)} AS x FROM orders")
_P = lambda: Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
add("window_rank", lambda t: t("customer").select("c_custkey", F.rank().over(_P()).alias("r"), F.dense_rank().over(_P()).alias("d")), "SELECT c_custkey, (rank() OVER w)::INTEGER AS r, (dense_rank() OVER w)::INTEGER AS d FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
add("window_running_sum", lambda t: t("orders").select("o_orderkey", r2(F.sum("o_totalprice").over(_W().rowsBetween(-2, 0)), "s", 2)), "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS s FROM orders")
add("window_time_range", lambda t: t("events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM events")
add("window_first_last", lambda t: t("orders").select("o_orderkey", F.first("o_orderkey").over(_W()).alias("f"), F.last("o_orderkey").over(_W().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("l")), f"SELECT o_orderkey, first_value(o_orderkey) {_SW} AS f, last_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS l FROM orders")
# --- order and sets
add("sort_limit", lambda t: t("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
add("sort_offset", lambda t: t("orders").orderBy("o_orderkey").offset(100).limit(50).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 50 OFFSET 100")
add("sort_top_per_group", lambda t: t("customer").withColumn("r", F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey"))).where("r <= 3").select("c_nationkey", "c_custkey"), "SELECT c_nationkey, c_custkey FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) <= 3")
_A, _B = ("SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F'", "SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'O'")
_sets = lambda t: tuple(t("orders").where(F.col("o_orderstatus") == s).select(F.col("o_custkey").alias("k")) for s in "FO")
for fn, call, word in (("union_all", "unionAll", "UNION ALL"), ("intersect", "intersect", "INTERSECT"), ("intersect_all", "intersectAll", "INTERSECT ALL"), ("except", "subtract", "EXCEPT"), ("except_all", "exceptAll", "EXCEPT ALL")):
    add(f"setop_{fn}", lambda t, call=call: getattr(_sets(t)[0], call)(_sets(t)[1]), f"{_A} {word} {_B}")
add("setop_union_distinct", lambda t: _sets(t)[0].union(_sets(t)[1]).distinct(), f"{_A} UNION {_B}")
# --- scalar functions
add("fn_string", lambda t: t("part").select("p_partkey", F.split_part("p_name", F.lit(" "), F.lit(1)).alias("a"), F.initcap("p_name").alias("b"), F.translate("p_type", "AEIOU", "aeiou").alias("c"), F.regexp_replace("p_brand", "#([0-9]+)", "-$1").alias("d"), F.reverse("p_name").alias("e"), F.lpad("p_brand", 12, "*").alias("f"), F.levenshtein("p_name", "p_type").alias("g")),
    r"SELECT p_partkey, split_part(p_name, ' ', 1) AS a, array_to_string(list_transform(string_split(p_name, ' '), lambda w: upper(w[1]) || lower(w[2:])), ' ') AS b, translate(p_type, 'AEIOU', 'aeiou') AS c, regexp_replace(p_brand, '#([0-9]+)', '-\1', 'g') AS d, reverse(p_name) AS e, lpad(p_brand, 12, '*') AS f, levenshtein(p_name, p_type)::INTEGER AS g FROM part")
add("fn_date", lambda t: t("orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.dayofweek("o_orderdate").alias("dow"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("m"), F.datediff(F.lit("2002-01-01").cast("date"), F.col("o_orderdate")).alias("age"), F.date_format("o_orderdate", "yyyyMMdd").alias("s")),
    "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, (dayofweek(o_orderdate) + 1)::INTEGER AS dow, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, date_diff('day', o_orderdate::DATE, DATE '2002-01-01')::INTEGER AS age, strftime(o_orderdate, '%Y%m%d') AS s FROM orders")
add("fn_math", lambda t: t("part").select("p_partkey", r2(F.ln("p_retailprice"), "a", 6), r2(F.sqrt("p_retailprice"), "b", 6), F.pmod(-F.col("p_size"), F.lit(7)).alias("c"), F.greatest("p_size", F.lit(20)).alias("d"), r2(F.log10("p_retailprice"), "e", 6), F.floor(F.col("p_retailprice") / 7).alias("f")),
    "SELECT p_partkey, round(ln(p_retailprice), 6) AS a, round(sqrt(p_retailprice), 6) AS b, (((-p_size % 7) + 7) % 7)::INTEGER AS c, greatest(p_size, 20)::INTEGER AS d, round(log10(p_retailprice), 6) AS e, floor(p_retailprice / 7)::BIGINT AS f FROM part")
add("fn_array", lambda t: t("documents").select("doc_id", F.split("text", " ").alias("w")).select("doc_id", F.size("w").alias("n"), F.size(F.array_distinct("w")).alias("d"), F.aggregate("w", F.lit(0), lambda a, x: a + F.length(x)).alias("chars"), F.array_join(F.slice("w", 1, 3), "|").alias("head"), F.size(F.filter("w", lambda x: F.length(x) > 8)).alias("long")),
    "WITH s AS (SELECT doc_id, string_split(text, ' ') AS w FROM documents) SELECT doc_id, len(w)::INTEGER AS n, len(list_distinct(w))::INTEGER AS d, list_sum(list_transform(w, lambda x: length(x)))::INTEGER AS chars, array_to_string(w[1:3], '|') AS head, len(list_filter(w, lambda x: length(x) > 8))::INTEGER AS long FROM s")
add("fn_map", lambda t: t("orders").groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct(F.col("o_orderkey").cast("string"), "o_totalprice"))).alias("m")).select("o_orderstatus", F.size("m").alias("n"), F.size(F.map_filter("m", lambda k, v: v > 100000)).alias("dear")), "SELECT o_orderstatus, count(*)::INTEGER AS n, (count(*) FILTER (o_totalprice > 100000))::INTEGER AS dear FROM orders GROUP BY 1")
add("fn_json", lambda t: t("events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("k2"), F.to_json(F.struct("user_id")).alias("j")), "SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k, json_extract_string(props, '$.k')::INTEGER AS k2, '{\"user_id\":' || user_id || '}' AS j FROM events")
add("fn_variant", lambda t: t("events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")), "SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM events")
add("fn_url", lambda t: t("pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PROTOCOL")).alias("scheme")), r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, regexp_extract(url, '^([a-z]+)://', 1) AS scheme FROM pages")
add("fn_hash", lambda t: t("part").select("p_partkey", F.md5("p_name").alias("m"), F.sha2("p_name", 256).alias("s")), "SELECT p_partkey, md5(p_name) AS m, sha256(p_name) AS s FROM part")
add("fn_decimal", lambda t: t("orders").groupBy("o_orderstatus").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("string").alias("total")), "SELECT o_orderstatus, sum(o_totalprice::DECIMAL(18,2))::VARCHAR AS total FROM orders GROUP BY 1")


def _vectors(t):
    e = t("embeddings")
    first = F.broadcast(e.where("vec_id = 0").select(F.col("embedding").alias("q")))
    a, b = F.col("embedding"), F.col("q")
    return e.crossJoin(first).select("vec_id", r2(dot(a, b), "dot", 5), r2(norm(a), "norm", 5), r2(cosine(a, b), "cosine", 5), r2(euclidean(a, b), "distance", 4))


add("vector_functions", _vectors, "WITH q AS (SELECT embedding::DOUBLE[] AS q FROM embeddings WHERE vec_id = 0), e AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) SELECT vec_id, round(list_dot_product(v, q), 5) AS dot, round(sqrt(list_dot_product(v, v)), 5) AS norm, round(list_cosine_similarity(v, q), 5) AS cosine, round(list_distance(v, q), 4) AS distance FROM e, q")


# --- sources and sinks: written to the shared folder and read back
def _round_trip(fmt: str, write=None, read=None):
    def query(t) -> DataFrame:
        df = t("nation")
        spark: SparkSession = df.sparkSession
        path = f"{shared_dir(spark).rstrip('/')}/sink-{uuid.uuid4().hex}"
        (write or (lambda w: w))(df.write.format(fmt)).save(path)
        return (read or (lambda r: r))(spark.read.schema(df.schema).format(fmt)).load(path).select("n_nationkey", "n_name", "n_regionkey")

    return query


_NATION = "SELECT n_nationkey, n_name, n_regionkey FROM nation"
add("io_parquet_roundtrip", _round_trip("parquet", lambda w: w.partitionBy("n_regionkey")), _NATION)
add("io_csv_roundtrip", _round_trip("csv", lambda w: w.option("header", True), lambda r: r.option("header", True)), _NATION)
add("io_json_roundtrip", _round_trip("json"), _NATION)
add("io_orc_roundtrip", _round_trip("orc"), _NATION)


def _text_lines(t) -> DataFrame:
    df = t("nation").select(F.concat_ws("\t", "n_nationkey", "n_name").alias("value"))
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/sink-{uuid.uuid4().hex}"
    df.write.text(path)
    return df.sparkSession.read.text(path)


add("io_text_roundtrip", _text_lines, "SELECT n_nationkey || chr(9) || n_name AS value FROM nation")


def _bucketed(t) -> DataFrame:
    spark = t("nation").sparkSession
    name = f"bucketed_{uuid.uuid4().hex}"
    t("customer").select("c_custkey", "c_nationkey").write.bucketBy(4, "c_nationkey").saveAsTable(name)
    return spark.table(name).groupBy("c_nationkey").agg(F.count("*").alias("n"))


add("io_bucketed_table", _bucketed, "SELECT c_nationkey, count(*) AS n FROM customer GROUP BY 1")
