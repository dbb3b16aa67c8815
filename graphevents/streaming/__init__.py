"""The methods on unbounded input: grounding, windows, sessions, late rows, scoring in micro-batches."""

from __future__ import annotations

import shutil
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.components import checkpointed


def events_stream(spark: SparkSession, path: str) -> DataFrame:
    """The events as a stream of files; their time is cast, since watermarks refuse times without a zone."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything a stream of the files that are there gives, read back as a table."""
    spark = stream.sparkSession
    name, place = f"drained_{uuid.uuid4().hex}", tempfile.mkdtemp(prefix="stream-")
    base = spark.sparkContext.getCheckpointDir() or place
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/{name}").start()
    q.awaitTermination()
    out = checkpointed(spark.table(name))
    spark.catalog.dropTempView(name)
    shutil.rmtree(place, ignore_errors=True)
    return out


def tumbling(events: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """``start, event_type, n`` of fixed (or sliding) windows."""
    return events.groupBy(F.window("ts", width, slide or width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """``user_id, start, n``: runs of a user's events without a longer gap."""
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select("user_id", F.col("session_window.start").alias("start"), "n")


def nested_sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Sessions as sentences: a purchase is an event, an error before it in the session a negative regulation of it."""
    first = lambda what: F.min(F.when(F.col("event_type") == what, F.col("ts")))
    last = F.max(F.when(F.col("event_type") == "purchase", F.col("ts")))
    s = events.groupBy(F.session_window("ts", gap), "user_id").agg(first("error").alias("error"), last.alias("purchase"))
    return s.filter("purchase is not null").select("user_id", F.col("session_window.start").alias("start"), F.when(F.col("error") < F.col("purchase"), "Negative(purchase)").otherwise("purchase").alias("event"))


def error_then_purchase(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Pairs of a user's error and a purchase within an hour after it, as a stream-stream join with bounded state."""
    e = events.filter("event_type = 'error'").select(F.col("user_id").alias("u"), F.col("ts").alias("error_ts"), F.col("event_id").alias("error_id")).withWatermark("error_ts", "2 hours")
    p = events.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("purchase_ts"), F.col("event_id").alias("purchase_id")).withWatermark("purchase_ts", "2 hours")
    on = (F.col("u") == F.col("user_id")) & (F.col("purchase_ts") >= F.col("error_ts")) & (F.col("purchase_ts") <= F.col("error_ts") + F.expr(f"interval {within}"))
    return e.join(p, on).select("user_id", "error_id", "purchase_id")


def late_rows(events: DataFrame, delay_seconds: int = 3600) -> DataFrame:
    """``file_part, rows, late``: rows of a replay that come after the watermark of what came before them, by parts of the replay."""
    from pyspark.sql import Window

    parts = events.groupBy("part").agg(F.max("ts").alias("latest"))
    seen = parts.withColumn("mark", F.max("latest").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)))  # a row a part of the replay
    return events.join(F.broadcast(seen), "part").groupBy("part").agg(F.count("*").alias("rows"), F.count_if(F.col("ts") < F.col("mark") - F.expr(f"interval {delay_seconds} seconds")).alias("late"))


def ground_stream(sentences: DataFrame, dictionary: DataFrame) -> DataFrame:
    """A stream of sentences joined with a static dictionary: ``sent_id, tok_from, tok_to, concept_id``."""
    from .. import ground

    return ground.match_ngrams(sentences, dictionary)


def score_stream(rows: DataFrame, predict: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Micro-batches through a trained model, whose parameters are static."""
    return predict(rows)


def upsert(path: str) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` sink that is safe to repeat: each batch overwrites its own folder."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def open_events(pieces: DataFrame, timeout_ms: int = 3_600_000, delay: str = "1 hour") -> DataFrame:
    """Holds an event until its trigger and theme have both arrived: ``trig_id, what (trigger or theme), value, ts`` -> trig_id, etype, theme.

    State is one pair of strings an open event; it is dropped once the watermark is ``timeout_ms`` beyond the piece that came last. Time is
    that of the rows, so a replay gives the same result and ends.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        etype, theme = state.get if state.exists else (None, None)
        if state.hasTimedOut:
            state.remove()
            return
        latest = 0
        for f in frames:
            latest = max(latest, int(f["ts"].max().timestamp() * 1000))
            for what, value in zip(f["what"], f["value"], strict=True):
                etype, theme = (value, theme) if what == "trigger" else (etype, value)
        if etype and theme:
            if state.exists:
                state.remove()
            yield pd.DataFrame({"trig_id": [key[0]], "etype": [etype], "theme": [theme]})
        else:
            state.update((etype, theme))
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), latest) + timeout_ms)

    return pieces.withWatermark("ts", delay).groupBy("trig_id").applyInPandasWithState(step, "trig_id long, etype string, theme string", "etype string, theme string", "append", GroupStateTimeout.EventTimeTimeout)
