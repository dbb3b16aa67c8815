"""Streams over the event table, each against its batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import ground, streaming
from ..sources import notes
from ..sources.tables import load
from .base import Work, with_notes
from .graphs import DICTIONARY, MATCHES

QUERIES: dict = {}


def put(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = (f, sql)
        return f

    return add


def ntz(df):
    return df.withColumn("start", F.col("start").cast("timestamp_ntz"))


TUMBLING = "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL"
SESSION = (
    "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM "
    "(SELECT user_id, ts, event_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s"
)


@put("stream_tumbling", TUMBLING)
def _(spark, sf):
    return ntz(streaming.drained(streaming.tumbling(streaming.events_stream(spark, f"{sf}/events.parquet")), "complete"))


@put("stream_sliding", "SELECT start, event_type, count(*) AS n FROM (SELECT event_type, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS start FROM events) GROUP BY ALL")
def _(spark, sf):
    return ntz(streaming.drained(streaming.tumbling(streaming.events_stream(spark, f"{sf}/events.parquet"), "2 hours", "1 hour"), "complete"))


@put("stream_session", SESSION)
def _(spark, sf):
    return ntz(streaming.drained(streaming.sessions(streaming.events_stream(spark, f"{sf}/events.parquet")), "complete"))


@put("stream_nested_events", f"SELECT event, count(*) AS n FROM (SELECT CASE WHEN min(CASE WHEN event_type = 'error' THEN ts END) < max(CASE WHEN event_type = 'purchase' THEN ts END) THEN 'Negative(purchase)' ELSE 'purchase' END AS event FROM ({SESSION.replace('SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, ', 'SELECT user_id, s, ts, event_type FROM (SELECT user_id, ts, event_type, ').replace('(SELECT user_id, ts, event_id,', '(SELECT user_id, ts, event_id, event_type,').replace(' GROUP BY user_id, s', '')}) GROUP BY user_id, s HAVING count(*) FILTER (event_type = 'purchase') > 0) GROUP BY event")
def _(spark, sf):
    s = streaming.drained(streaming.nested_sessions(streaming.events_stream(spark, f"{sf}/events.parquet")), "complete")
    return s.groupBy("event").agg(F.count("*").alias("n"))


@put("stream_dedup", "SELECT event_type, count(*) AS n FROM (SELECT DISTINCT user_id, event_type FROM events) GROUP BY event_type")
def _(spark, sf):
    e = streaming.events_stream(spark, f"{sf}/events.parquet")
    return streaming.drained(e.dropDuplicates(["user_id", "event_type"]).select("user_id", "event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


@put("stream_interval_join", "SELECT e.user_id, e.event_id AS error_id, p.event_id AS purchase_id FROM events e JOIN events p ON e.user_id = p.user_id AND e.event_type = 'error' AND p.event_type = 'purchase' AND p.ts >= e.ts AND p.ts <= e.ts + INTERVAL 1 HOUR")
def _(spark, sf):
    return streaming.drained(streaming.error_then_purchase(streaming.events_stream(spark, f"{sf}/events.parquet")))


@put("stream_late_rows", "WITH e AS (SELECT ts, event_id % 10 AS part FROM events), m AS (SELECT part, max(max(ts)) OVER (ORDER BY part ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS mark FROM e GROUP BY part) SELECT e.part, count(*) AS rows, count(*) FILTER (ts < mark - INTERVAL 3600 SECOND) AS late FROM e JOIN m USING (part) GROUP BY e.part")
def _(spark, sf):
    return streaming.late_rows(load(spark, sf, "events").withColumn("part", F.col("event_id") % 10))


@put("stream_ground_micro_batch", with_notes(DICTIONARY, MATCHES) + "SELECT concept_id, count(*) AS n FROM m GROUP BY concept_id")
def _(spark, sf):
    from ..operators.components import checkpointed

    w = Work(spark, sf)
    checkpointed(spark.range(1))  # so that the shared folder is known
    place = f"{spark.sparkContext.getCheckpointDir()}/sentences-{abs(hash(sf))}"
    w.sentences.select("sent_id", "text").write.mode("overwrite").parquet(place)
    stream = spark.readStream.schema("sent_id long, text string").parquet(place)
    return streaming.drained(streaming.ground_stream(stream, ground.dictionary(spark, sf))).groupBy("concept_id").agg(F.count("*").alias("n"))


@put("stream_batch_equals_stream", "SELECT 0::BIGINT AS differences")
def _(spark, sf):
    batch = streaming.tumbling(load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")))
    stream = streaming.drained(streaming.tumbling(streaming.events_stream(spark, f"{sf}/events.parquet")), "complete")
    return batch.exceptAll(stream).union(stream.exceptAll(batch)).agg(F.count("*").alias("differences"))


@put("stream_open_events", with_notes("a AS (SELECT trig_id, min(ref) AS theme FROM note_arguments WHERE role = 'Theme' AND kind = 'entity' AND trig_id % 10 = 1 GROUP BY trig_id)") + "SELECT trig_id, etype, CAST(theme AS VARCHAR) AS theme FROM note_triggers JOIN a USING (trig_id)")
def _(spark, sf):
    from ..operators.components import checkpointed

    w = Work(spark, sf)
    checkpointed(spark.range(1))
    place = f"{spark.sparkContext.getCheckpointDir()}/pieces-{abs(hash(sf))}"
    t = notes.triggers(w.lines).filter("trig_id % 10 = 1").select("trig_id", F.lit("trigger").alias("what"), F.col("etype").alias("value"))
    a = notes.arguments(w.lines).filter("role = 'Theme' and kind = 'entity' and trig_id % 10 = 1").groupBy("trig_id").agg(F.min("ref").cast("string").alias("value")).select("trig_id", F.lit("theme").alias("what"), "value")
    t.union(a).withColumn("ts", F.timestamp_seconds(F.col("trig_id") % 600)).repartition(4).write.mode("overwrite").parquet(place)
    stream = spark.readStream.schema("trig_id long, what string, value string, ts timestamp").option("maxFilesPerTrigger", 2).parquet(place)
    return streaming.drained(streaming.open_events(stream))
