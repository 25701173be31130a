"""Descent on a stream, and event-time windows over the events table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gossamer.config import DescentConfig
from gossamer.functions.arrays import hash_hex, hash_int
from gossamer.operators.descent import as_array, average, first, folded
from gossamer.operators.draws import exact_rank

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def slice_rounds(points: DataFrame, cfg: DescentConfig) -> DataFrame:
    """All samples of a micro-batch as rounds of every worker: the worker by hash, the order by hash, the last round smaller."""
    placed = points.withColumn("worker", F.pmod(hash_int(F.lit(cfg.seed), F.lit("part"), "sample_id"), F.lit(cfg.workers)).cast("int"))
    order = hash_hex(F.lit(cfg.seed), F.lit("order"), "sample_id")
    ranked = exact_rank(placed, order, "sample_id", by=("worker",), groups=cfg.workers)
    return ranked.select("worker", F.floor(F.col("rank") / cfg.b).cast("int").alias("round"), F.pmod("rank", F.lit(cfg.b)).cast("int").alias("slot"), "x")


def advanced(points: DataFrame, cfg: DescentConfig, w: list) -> list:
    """The state after one micro-batch: as many rounds as its samples need; an empty one changes nothing."""
    drawn = slice_rounds(points, cfg).persist()
    try:
        last = drawn.agg(F.max("round")).first()[0]
        if last is None:
            return w
        states = folded(drawn, cfg.with_(steps=last + 1), w)
        return as_array(average(states) if cfg.final == "average" else first(states)).tolist()
    finally:
        drawn.unpersist()


def descend_stream(stream: DataFrame, cfg: DescentConfig, w0: list, store: str, checkpoint: str):
    """Continues a model by every micro-batch; the state after batch ``i`` is ``store/i``, so a replayed batch changes nothing."""

    def advance(batch: DataFrame, batch_id: int) -> None:
        own = batch.sparkSession
        w = w0 if batch_id == 0 else [list(r.v) for r in own.read.parquet(f"{store}/{batch_id - 1}").orderBy("block").collect()]
        rows = advanced(batch, cfg, w)
        own.createDataFrame(list(enumerate(rows)), "block int, v array<double>").coalesce(1).write.mode("overwrite").parquet(f"{store}/{batch_id}")

    return stream.writeStream.foreachBatch(advance).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def hourly(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events of a stream in tumbling hours, kept while the watermark allows: what comes later is left out by the engine."""
    timed = events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", delay)
    return timed.groupBy(F.window("at", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.unix_micros("w.start").alias("start_us"), "n")


def played(rows: DataFrame, mode: str, store: str, checkpoint: str) -> None:
    """Runs a stream to the end of its input. ``complete``: the last result is in ``store``; ``update``: the changes of
    batch ``i`` are in ``store/batch=i``. A batch that is run again writes the same folder again."""

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(store if mode == "complete" else f"{store}/batch={batch_id}")

    rows.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def raw(spark: SparkSession, folder: str, per_trigger: int = 1) -> DataFrame:
    """Events of a folder of Parquet files, as a stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(folder)


def replay(spark: SparkSession, folder: str, per_trigger: int = 1) -> DataFrame:
    """Event points of a folder of Parquet files, as a stream."""
    return raw(spark, folder, per_trigger).select(F.col("event_id").cast("string").alias("sample_id"), F.array(F.col("value") / 600.0, F.hour("ts") / 24.0, F.get_json_object("props", "$.k").cast("double") / 100.0).alias("x"))


def windows(events: DataFrame, kind: str) -> DataFrame:
    """Counts of events in tumbling hours, sliding two-hour windows, or sessions of a user with gaps of half an hour."""
    timed = events.withColumn("at", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        timed = timed.withWatermark("at", "1 hour")
    if kind == "session":
        span = F.session_window("at", "30 minutes")
        return timed.groupBy(span.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_micros("w.start").alias("start_us"), F.unix_micros("w.end").alias("end_us"), "n")
    span = F.window("at", "1 hour") if kind == "tumbling" else F.window("at", "2 hours", "30 minutes")
    return timed.groupBy(span.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select("event_type", F.unix_micros("w.start").alias("start_us"), "n", "total")


