"""Continuous monitoring: windowed series, and a flag for each series from clustering features kept as state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from edgeloc.operators.birch import BETA, Tree
from edgeloc.sources.tables import EVENTS


def event_stream(spark: SparkSession, folder: str, files: int = 1) -> DataFrame:
    """Event files of a folder as they come."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).option("pathGlobFilter", "events*.parquet").parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def daily_series(events: DataFrame, late: str = "1 day", dedupe: bool = False) -> DataFrame:
    """(day, event_type, n, total): tumbling days with a watermark; the same expression for a batch and a stream."""
    e = events.withWatermark("ts", late)
    e = e.dropDuplicatesWithinWatermark(["event_id"]) if dedupe and events.isStreaming else e
    return e.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents")).select(F.datediff(F.col("w.start").cast("date"), F.lit("2024-01-01").cast("date")).alias("day"), "event_type", "n", "cents")


def flags(samples: DataFrame, beta: float = BETA, order: tuple[str, ...] = ("ts", "event_id")) -> DataFrame:
    """(entity, n_features, is_anomalous) updates of a stream of (entity, value, order columns).

    A micro-batch's samples of an entity are sorted by order before they are taken; across batches they are taken as batches come, so a replay equals the batch
    result if files come in order. All features are kept: their number is bounded by the range of values over beta, not by time.
    """

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, ls, ss = state.get if state.exists else ([], [], [])
        t = Tree(beta, 1 << 30)
        t.root["cf"] = [(a, pd.Series([b]).to_numpy(), c) for a, b, c in zip(n, ls, ss)]
        for x in pd.concat(batches, ignore_index=True).sort_values(list(order), kind="stable")["value"]:
            t.insert(x)
        leaves = t.leaves()
        state.update(([float(c[0]) for c in leaves], [float(c[1][0]) for c in leaves], [float(c[2]) for c in leaves]))
        yield pd.DataFrame({"entity": [key[0]], "n_features": [len(leaves)], "is_anomalous": [len(leaves) > 1]})

    return samples.groupBy("entity").applyInPandasWithState(run, "entity string, n_features int, is_anomalous boolean", "n array<double>, ls array<double>, ss array<double>", "update", GroupStateTimeout.NoTimeout)


def to_incidents(flagged: DataFrame, folder: str, checkpoint: str, **trigger) -> StreamingQuery:
    """Writes each micro-batch's flagged entities under folder, one directory for each batch: a batch that is run again replaces its own."""

    def write(batch: DataFrame, number: int) -> None:
        batch.where("is_anomalous").withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{folder}/batch={number}")

    return flagged.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def with_services(metric: DataFrame, services: DataFrame) -> DataFrame:
    """A stream of (service, ...) beside the static (service, device): a stream-static join."""
    return metric.join(services, "service")


def with_latency(metric: DataFrame, latency: DataFrame, late: str = "1 day", within: str = "1 hour") -> DataFrame:
    """Metric samples (service, ts, value) with the service's latency samples (service, at, latency) of the time before them: a join of two streams, whose state the watermarks bound."""
    m, n = metric.withWatermark("ts", late), latency.withColumnRenamed("service", "called").withWatermark("at", late)
    return m.join(n, F.expr(f"service = called AND at <= ts AND at >= ts - interval {within}")).drop("called")


def run_once(df: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Processes what is there, into a table in memory: for tests and small results, on a driver that keeps its own checkpoint."""
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)
