"""Streams over the events table as a file source; each runs to the end of what is there and returns what its sink got."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from reportgraph.operators import service
from reportgraph.sources.corpus import EVENT_TEXT
from reportgraph.sources.io import read_table, shared_dir


def event_stream(spark: SparkSession, sf_dir: str, watermark: str | None = "10 minutes", path: str | None = None, files: int = 1000) -> DataFrame:
    """Events with ``ts`` as TIMESTAMP, which watermarks need; of the table, or of files as they come to the folder ``path``, so many a batch."""
    schema = read_table(spark, sf_dir, "events").schema
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path or f"{sf_dir}/events.parque[t]").withColumn("ts", F.col("ts").cast("timestamp"))
    return s.withWatermark("ts", watermark) if watermark else s


def run(stream: DataFrame, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Runs a stream over all that is available into Parquet under the shared folder, and reads it.

    Complete mode keeps the last batch. Update mode keeps, for each of the ``keys``, the row of the last batch that had one; batches are
    written by number, so one that is tried again replaces itself.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).outputMode("append").start()
    else:
        def put(batch: DataFrame, n: int) -> None:
            batch.write.mode("overwrite").parquet(f"{base}/out/batch={n}" if mode == "update" else f"{base}/out")

        q = stream.writeStream.foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).outputMode(mode).start()
    q.awaitTermination()
    if mode == "update":
        rows = spark.read.parquet(f"{base}/out")
        last = rows.groupBy(*keys).agg(F.max_by(F.struct(*stream.columns), "batch").alias("r"))
        return last.select("r.*")
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def _times(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in cols})


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = event_stream(spark, sf_dir).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return _times(run(w, "complete").select(F.col("window.start").alias("day"), "event_type", "n"), "day")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = event_stream(spark, sf_dir).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return _times(run(w, "complete").select(F.col("window.start").alias("start"), "n"), "start")


def session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of users with a gap of six hours."""
    w = event_stream(spark, sf_dir).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"))
    return run(w, "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event once, though every one comes twice."""
    s = event_stream(spark, sf_dir).select("event_id", "ts")
    twice = s.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    return run(twice.dropDuplicatesWithinWatermark(["event_id"])).select("event_id")


def static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read_table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    return run(event_stream(spark, sf_dir, None).join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors and the same user's logins within six hours after, stream to stream; state is dropped by the watermarks."""
    e = event_stream(spark, sf_dir)
    a = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("u"), F.col("ts").alias("t0"))
    b = event_stream(spark, sf_dir).where("event_type = 'login'").select(F.col("event_id").alias("login_id"), "user_id", "ts")
    return run(a.join(b, F.expr("u = user_id AND ts >= t0 AND ts < t0 + INTERVAL 6 HOURS")).select("error_id", "login_id"))


def auto_trigger(spark: SparkSession, sf_dir: str, teams: tuple[str, ...] = ("error", "login"), model=None) -> DataFrame:
    """Candidates of the enabled teams' reports, or a tagger's mentions in them, by the same code as on tables."""
    s = event_stream(spark, sf_dir, None)
    reports = s.select(F.col("event_id").alias("report_id"), F.expr(EVENT_TEXT).alias("description"), F.col("event_type").alias("team"))
    return run(service.auto(reports, teams, model))


def life_cycle(spark: SparkSession, sf_dir: str, path: str | None = None, files: int = 1000) -> DataFrame:
    """Incidents of each user opened by an error and closed by a login, kept as a count and an open flag in state.

    Events of one batch are read in order of time; batches are taken to follow each other in time.
    """
    s = event_stream(spark, sf_dir, None, path, files).select("user_id", "ts", "event_id", "event_type")

    def step(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        before = state.get if state.exists else (False, 0)
        is_open, closed = opened_and_closed(*before, pd.concat(parts).sort_values(["ts", "event_id"])["event_type"])
        state.update((is_open, closed))
        yield pd.DataFrame({"user_id": [key[0]], "is_open": [is_open], "closed": [closed]})

    out = s.groupBy("user_id").applyInPandasWithState(step, "user_id long, is_open boolean, closed long", "is_open boolean, closed long", "update", "NoTimeout")
    return run(out, "update", ("user_id",))


def opened_and_closed(is_open: bool, closed: int, types: Iterable[str]) -> tuple[bool, int]:
    """An error opens an incident, a login closes it."""
    for t in types:
        if t == "error":
            is_open = True
        elif t == "login" and is_open:
            is_open, closed = False, closed + 1
    return is_open, closed


class LifeCycle(StatefulProcessor):
    """The life cycle of a user's incidents as a value in the state store."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.cycle = handle.getValueState("cycle", "is_open boolean, closed long")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        before = self.cycle.get() if self.cycle.exists() else (False, 0)
        after = opened_and_closed(bool(before[0]), int(before[1]), pd.concat(rows).sort_values(["ts", "event_id"])["event_type"])
        self.cycle.update(after)
        yield pd.DataFrame({"user_id": [key[0]], "is_open": [after[0]], "closed": [after[1]]})

    def close(self) -> None:
        pass


STATE_STORE = "spark.sql.streaming.stateStore.providerClass"


def life_cycle_processor(spark: SparkSession, sf_dir: str, path: str | None = None, files: int = 1000) -> DataFrame:
    """The same life cycles by a stateful processor, whose state the store on disk keeps; the session's store is as before when it ends."""
    s = event_stream(spark, sf_dir, None, path, files).select("user_id", "ts", "event_id", "event_type")
    out = s.groupBy("user_id").transformWithStateInPandas(LifeCycle(), "user_id long, is_open boolean, closed long", "update", "none")
    kept = spark.conf.get(STATE_STORE, None)
    spark.conf.set(STATE_STORE, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return run(out, "update", ("user_id",))
    finally:
        if kept is None:
            spark.conf.unset(STATE_STORE)
        else:
            spark.conf.set(STATE_STORE, kept)


def late_rows(spark: SparkSession, sf_dir: str, path: str | None = None, files: int = 1000) -> DataFrame:
    """Rows of each type that came in time and that came later than the watermark of an hour allows, by the largest time of the batches before."""
    s = event_stream(spark, sf_dir, None, path, files).select("event_type", "ts")
    base = f"{shared_dir(spark).rstrip('/')}/late-{uuid.uuid4().hex}"

    def put(batch: DataFrame, n: int) -> None:
        before = spark.read.parquet(f"{base}/out").where(F.col("batch") < n).agg(F.max("top")).first()[0] if n else None
        late = F.lit(False) if before is None else F.col("ts") < F.lit(before) - F.expr("INTERVAL 1 HOUR")
        batch.groupBy("event_type", late.alias("late")).agg(F.count("*").alias("n"), F.max("ts").alias("top")).write.mode("overwrite").parquet(f"{base}/out/batch={n}")

    s.writeStream.foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{base}/out").groupBy("event_type", "late").agg(F.sum("n").alias("n"))


LIFE_CYCLE_SQL = """WITH e AS (SELECT user_id, ts, event_id, event_type FROM events WHERE event_type IN ('error', 'login')),
 s AS (SELECT *, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM e),
 u AS (SELECT DISTINCT user_id FROM events)
 SELECT user_id, coalesce(bool_or(after IS NULL AND event_type = 'error'), false) AS is_open, count(*) FILTER (event_type = 'login' AND before = 'error') AS closed FROM u LEFT JOIN s USING (user_id) GROUP BY user_id"""

STREAMS: dict[str, tuple[Callable, str | None]] = {
    "stream_tumbling": (tumbling, "SELECT date_trunc('day', ts)::TIMESTAMP AS day, event_type, count(*) AS n FROM events GROUP BY ALL"),
    "stream_sliding": (sliding, "SELECT d AS start, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts)::TIMESTAMP, date_trunc('day', ts)::TIMESTAMP - INTERVAL 1 DAY]) AS d FROM events) GROUP BY d"),
    "stream_session": (session, "WITH g AS (SELECT user_id, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOURS OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events) SELECT user_id, sum(new)::BIGINT AS sessions, count(*) AS events FROM g GROUP BY user_id"),
    "stream_dedup": (dedup, "SELECT event_id FROM events"),
    "stream_static_join": (static_join, "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey"),
    "stream_interval_join": (interval_join, "SELECT a.event_id AS error_id, b.event_id AS login_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 6 HOURS WHERE a.event_type = 'error' AND b.event_type = 'login'"),
    "stream_auto_trigger": (auto_trigger, f"WITH l AS (SELECT event_id AS report_id, unnest(string_split({EVENT_TEXT}, chr(10))) AS s, unnest(range(0, 3)) AS sent_no FROM events WHERE event_type IN ('error', 'login')) SELECT report_id, sent_no::INTEGER AS sent_no, split_part(s, ': ', 1) AS name, split_part(s, ': ', 2) AS value, 'key_value' AS pattern FROM l"),
    "stream_life_cycle": (life_cycle, LIFE_CYCLE_SQL),
    "stream_life_cycle_processor": (life_cycle_processor, LIFE_CYCLE_SQL),
    "stream_late_rows": (late_rows, "SELECT event_type, false AS late, count(*) AS n FROM events GROUP BY event_type"),
}
