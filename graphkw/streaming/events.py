"""Event streams: windows, late rows, duplicates, state, and a standing search."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphkw.schema import Graph, KeywordQuery
from graphkw.sources.tables import journeys, table
from graphkw.storage import shared_dir
from graphkw.streaming.incremental import Continuous


def _stream(spark: SparkSession, sf_dir: str, files: int = 2) -> DataFrame:
    """The events as a file stream of ``files`` files in the order of time."""
    path = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    events = table(spark, sf_dir, "events")
    events.repartitionByRange(files, "ts", "event_id").write.parquet(path)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all its input and returns what it wrote."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
    else:
        def put(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{base}/out")

        query = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def _windows(spark: SparkSession, sf_dir: str, *spans: str) -> DataFrame:
    counted = _stream(spark, sf_dir).groupBy(F.window("ts", *spans).alias("w"), "event_type").agg(F.count("*").alias("n"))
    return _drain(counted.select(F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start"), "event_type", "n"), "complete")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windows(spark, sf_dir, "1 hour")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windows(spark, sf_dir, "1 hour", "30 minutes")


def session(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = _stream(spark, sf_dir).groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return _drain(counted.select("user_id", F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start"), "n"), "complete")


def watermark_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly counts that close an hour after the latest event; what comes later than that is not counted."""
    counted = _stream(spark, sf_dir, 4).withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", "1 hour").groupBy(F.window("at", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return _drain(counted.select(F.col("w.start").cast("string").alias("start"), "n"))


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event twice in the stream, once out."""
    doubled = _stream(spark, sf_dir).withColumn("at", F.col("ts").cast("timestamp")).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return _drain(doubled.withWatermark("at", "40 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"))


def _last(key: tuple, frames, state: GroupState):
    ts, event, n = state.get if state.exists else (-1, -1, 0)
    for pdf in frames:
        for t, e in zip(pdf["t"], pdf["event_id"], strict=True):
            n += 1
            ts, event = max((ts, event), (int(t), int(e)))
    state.update((ts, event, n))
    yield pd.DataFrame({"user_id": [key[0]], "last_event": [event], "n": [n]})


def stateful_last(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's last event and number of events, updated by every batch."""
    rows = _stream(spark, sf_dir).select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    updates = rows.groupBy("user_id").applyInPandasWithState(_last, "user_id long, last_event long, n long", "t long, e long, n long", "update", GroupStateTimeout.NoTimeout)
    base = f"{shared_dir(spark)}/state-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("append").parquet(f"{base}/out")

    updates.writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{base}/out").groupBy("user_id").agg(F.max_by("last_event", "n").alias("last_event"), F.max("n").alias("n"))


def incremental_search(spark: SparkSession, sf_dir: str, keywords: tuple[str, ...] = ("purchase", "error"), tau: int = 4, k: int = 10) -> DataFrame:
    """Edges of the journeys arrive in two batches; the standing query's answers after the last."""
    g = journeys(spark, sf_dir)
    base = f"{shared_dir(spark)}/edges-{uuid.uuid4().hex}"
    g.edges.repartitionByRange(2, "src").write.parquet(f"{base}/in")
    standing: list[Continuous] = []
    empty = Graph(g.vertices, g.edges.limit(0), g.postings)
    standing.append(Continuous.start(empty, KeywordQuery(keywords, tau, k)))

    def step(batch: DataFrame, number: int) -> None:
        standing[0].insert(batch)

    stream: Callable = spark.readStream.schema("src long, dst long, w long").option("maxFilesPerTrigger", 1).parquet(f"{base}/in").writeStream.foreachBatch(step)
    stream.option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    return standing[0].answers()
