"""Report views over the star schema: the main corpus, its gold mentions, and the smaller corpora.

Each line of a report is a rule (condition, text, gold mentions) in expressions that Spark SQL and other
SQL dialects read alike, so the same rules also give the SQL of the view.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reportgraph.sources.io import read_table, tasks


@dataclass(frozen=True)
class Line:
    code: str
    when: str
    texts: tuple[str, ...]  # sentences; several for a two-column table
    gold: tuple[tuple[str, str], ...] = ()  # entity, value
    place: str = "kv"


IP = "'10.' || cast(cast(floor(c_custkey / 256) as bigint) % 256 as string) || '.' || cast(c_custkey % 256 as string) || '.' || cast(c_custkey % 7 as string)"
GUID = "'00000000-0000-4000-8000-' || lpad(hex(k), 12, '0')"
PRICE = "cast(cast(o_totalprice as decimal(18,2)) as string)"
NOTE = "substr(replace(b_text, chr(10), ' '), 1, 60)"
CALL = "case when k % 2 = 0 then 'true' else 'false' end"

LINES = (
    Line("greet", "true", ("'Hello support desk'",), (), "prose"),
    Line("kv1", "k % 2 = 0", ("case when k % 8 = 2 then 'The Customer Name: ' when k % 8 = 6 then 'Their Customer Name: ' else 'Customer Name: ' end || c_name",), (("customer name", "c_name"),)),
    Line("kv2", "k % 3 = 0", ("case when k % 9 = 0 then 'orderPriority: ' else 'Order Priority: ' end || o_orderpriority",), (("order priority", "o_orderpriority"),)),
    Line("kv3", "k % 2 = 1", ("'Order Status: ' || o_orderstatus",), (("order status", "o_orderstatus"),)),
    Line("tb", "k % 4 = 1", ("'Nation Name' || chr(9) || n_name", "'Region Name' || chr(9) || r_name", "'Market Segment' || chr(9) || c_mktsegment", f"'Total Price' || chr(9) || {PRICE}"), (("nation name", "n_name"), ("region name", "r_name"), ("market segment", "c_mktsegment"), ("total price", PRICE)), "table"),
    Line("kv4", "k % 5 = 0", (f"'Tracking Id: ' || {GUID}",), (("tracking id", GUID),)),
    Line("kv5", "k % 5 < 2", (f"'Source Ip: ' || case when k % 40 = 0 then 'true' else {IP} end",), (("source ip", f"case when k % 40 = 0 then 'true' else {IP} end"),)),
    Line("kv6", "k % 6 = 0", ("'Detail Link: ' || p_url",), (("detail link", "p_url"),)),
    Line("kv7", "k % 3 = 1", (f"'Needs Callback: ' || {CALL}",), (("needs callback", CALL),)),
    Line("kv8", "k % 10 = 4", (f"'Problem Note: ' || {NOTE}",), (("problem note", NOTE),)),
    Line("kv9", "k % 50 = 7", ("'Ship Zone: ' || r_name",), (("ship zone", "r_name"),)),
    Line("nz1", "k % 11 = 0", ("'Error 42 code: ' || cast(k as string)",)),
    Line("nz2", "k % 1499 = 3", ("'please escalate quickly: now'",)),
    Line("p0", "k % 4 = 0", (f"c_name || ' from ' || n_name || ' called about a delay and connected through ' || {IP}",), (("customer name", "c_name"), ("nation name", "n_name"), ("source ip", IP)), "prose"),
    Line("p1", "k % 4 = 1", (f"account of ' || c_name || ' misses parcel ' || {GUID}".replace("account of '", "'account of '", 1),), (("customer name", "c_name"), ("tracking id", GUID)), "prose"),
    Line("p2", "k % 4 = 2", ("'carrier for ' || n_name || ' in ' || r_name || ' reports a backlog'",), (("nation name", "n_name"), ("region name", "r_name")), "prose"),
    Line("p3", "k % 4 = 3", (f"'the ' || o_orderpriority || ' shipment worth ' || {PRICE} || ' left the dock late'",), (("order priority", "o_orderpriority"), ("total price", PRICE)), "prose"),
    Line("p4", "k % 101 = 5", (f"'refund of ' || {PRICE} || ' to ' || n_name || ' is open'",), (("total price", PRICE), ("nation name", "n_name")), "prose"),
    Line("p5", "k % 97 = 6", ("c_name || ' asked to raise it to ' || o_orderpriority",), (("customer name", "c_name"), ("order priority", "o_orderpriority")), "prose"),
    Line("p6", "k % 89 = 7", (f"'gateway ' || {IP} || ' in ' || r_name || ' was slow'",), (("source ip", IP), ("region name", "r_name")), "prose"),
)

TITLE = """case k % 6 when 0 then 'Parcel cannot be handed over - ' || lower(c_mktsegment) when 1 then 'Payment check hangs for ' || lower(r_name) || ' orders'
 when 2 then 'Address lookup returns nothing in ' || lower(r_name) when 3 then 'Carton count differs from invoice (' || lower(c_mktsegment) || ')'
 when 4 then 'Label printer offline near dock ' || lower(r_name) else 'Refund request waiting on approval - ' || lower(c_mktsegment) end"""
TEAM = "r_name || '/' || c_mktsegment"
WIDE_TABLE = "<table><tr><td>Queue</td><td>Depth</td><td>Limit</td></tr><tr><td>inbound</td><td>7</td><td>9</td></tr></table>"


def _description() -> str:
    """The body: lines that apply, joined by newlines; tables as markup on one line."""
    parts = []
    for x in LINES:
        text = x.texts[0]
        if x.place == "table":
            rows = [f"'<tr><td>' || replace({t}, chr(9), '</td><td>') || '</td></tr>'" for t in x.texts]
            text = "'<table>' || " + " || ".join(rows) + " || '</table>'"
        parts.append(f"case when {x.when} then {text} end")
        if x.code == "tb":
            parts.append(f"case when k % 7 = 3 then '{WIDE_TABLE}' end")
    return f"concat_ws(chr(10), {', '.join(parts)})"


DESCRIPTION = _description()

#: The row from which a report is made, as SQL.
BASE_SQL = """base AS (SELECT o_orderkey AS k, o.*, c_name, c_custkey, c_mktsegment, n_name, r_name, url AS p_url, b.text AS b_text
 FROM orders o JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
 JOIN pages ON page_id = o_orderkey % 50 JOIN benchmark b ON item_id = o_orderkey % 40)"""
REPORTS_SQL = f"""{BASE_SQL}, reports AS (SELECT k AS report_id, {TITLE} AS title, {DESCRIPTION} AS description, o_orderdate AS modified_at, {TEAM} AS team, o_orderstatus <> 'O' AS resolved FROM base)"""
#: Sentences straight from the rules, the check on cleaning.
SENTENCES_SQL = f"""{BASE_SQL}, line_list AS (SELECT k, list_filter([{', '.join(f'case when {x.when} then {t} end' for x in LINES for t in x.texts)}], lambda x: x IS NOT NULL) AS lines FROM base),
sentences AS (SELECT k AS report_id, unnest(range(0, len(lines))) AS sent_no, unnest(lines) AS text FROM line_list)"""
GOLD_SQL = f"{BASE_SQL}, gold AS (" + " UNION ALL ".join(f"SELECT k AS report_id, '{x.code}' AS line, '{x.place}' AS place, '{e}' AS entity, {v} AS value FROM base WHERE {x.when}" for x in LINES for e, v in x.gold) + ")"


def base_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each order with what its report is made of; the tables joined to it have a fixed number of rows for an order key.

    Orders are few bytes and their reports much work, so they are dealt to all tasks: a file's splits would leave most cores idle.
    """
    t = lambda n: read_table(spark, sf_dir, n)
    k = F.col("o_orderkey")
    pages = t("pages").where("page_id < 50").select(F.col("page_id"), F.col("url").alias("p_url"))
    bench = t("benchmark").where("item_id < 40").select(F.col("item_id"), F.col("text").alias("b_text"))
    places = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return (
        t("orders").repartition(tasks(spark), "o_orderkey").join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
        .join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
        .join(F.broadcast(pages), k % 50 == F.col("page_id")).join(F.broadcast(bench), k % 40 == F.col("item_id"))
        .withColumn("k", k)
    )


def order_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    return base_rows(spark, sf_dir).select(
        F.col("k").alias("report_id"), F.expr(TITLE).alias("title"), F.expr(DESCRIPTION).alias("description"),
        F.col("o_orderdate").alias("modified_at"), F.expr(TEAM).alias("team"), F.expr("o_orderstatus <> 'O'").alias("resolved"),
    )


def order_reports_gold(spark: SparkSession, sf_dir: str, only: DataFrame | None = None) -> DataFrame:
    """True mentions of the rendered reports: ``report_id, line, place, entity, value``, from one scan; of those with a ``report_id`` of ``only``, if it is given."""
    items = [F.when(F.expr(x.when), F.struct(F.lit(x.code).alias("line"), F.lit(x.place).alias("place"), F.lit(e).alias("entity"), F.expr(v).alias("value"))) for x in LINES for e, v in x.gold]
    rows = base_rows(spark, sf_dir)
    rows = rows if only is None else rows.join(only, rows["k"] == only["report_id"], "left_semi")
    rows = rows.select(F.col("k").alias("report_id"), F.explode(F.filter(F.array(*items), lambda m: m.isNotNull())).alias("m"))
    return rows.select("report_id", "m.*")


EVENT_TEXT = "'Event Type: ' || event_type || chr(10) || 'User Id: ' || cast(user_id as string) || chr(10) || 'Metric Value: ' || cast(value as string)"


def event_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as reports; only errors are incidents."""
    e = read_table(spark, sf_dir, "events")
    return e.select(
        F.col("event_id").alias("report_id"), F.concat(F.lit("Event of user "), F.col("user_id").cast("string")).alias("title"),
        F.concat(F.expr(EVENT_TEXT), F.lit("\nBatch Key: "), F.get_json_object("props", "$.k")).alias("description"),
        F.col("ts").alias("modified_at"), F.col("event_type").alias("team"), (F.col("event_type") == "error").alias("resolved"),
    )


def dialogs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One report for each conversation, its turns in order; a turn is bounded, a conversation has few of them."""
    c = read_table(spark, sf_dir, "conversations")
    turns = F.transform(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))), lambda t: F.concat(t["role"], F.lit(" said\n"), t["text"]))
    return c.groupBy(F.col("conv_id").alias("report_id")).agg(F.count("*").alias("turns"), F.array_join(turns, "\n").alias("description"))
