"""Reading the given tables, and the call and telemetry workloads made from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, fmt: str, path: str, schema: T.StructType) -> DataFrame:
    """Any built-in format, with a given schema: nothing is inferred."""
    return spark.read.schema(schema).format(fmt).load(path)


def write_partitioned(df: DataFrame, path: str, *cols: str) -> None:
    """Idempotent: a rerun replaces the partitions that it writes and no others."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*cols).parquet(path)


def supplier_spans(spark: SparkSession, sf_dir: str, timed: bool = True) -> DataFrame:
    """Spans of W-S: an order is a trace, a supplier a service, its nation a device; with timed, latency in days and the order's day, for which orders are joined."""
    place = load(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("device"))
    spans = load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("trace"), F.struct("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice").alias("pos"), F.col("l_suppkey").alias("service"), "l_shipdate")
    spans = spans.join(place, F.col("service") == F.col("s_suppkey"))
    if not timed:
        return spans.select("trace", "pos", "service", "device")
    order = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("trace"), "o_orderdate")
    return spans.join(order, "trace").select("trace", "pos", "service", "device", F.abs(F.datediff("l_shipdate", "o_orderdate")).alias("latency"), F.to_date("o_orderdate").alias("day"))


def event_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spans of W-E: a user is a trace; event type and fifth of props.k name the service, the fifth its device."""
    e = load(spark, sf_dir, "events").withColumn("device", F.floor(F.get_json_object("props", "$.k").cast("int") / 20))
    return e.select(F.col("user_id").alias("trace"), F.struct("ts", "event_id").alias("pos"), F.concat_ws("_", "event_type", F.col("device").cast("string")).alias("service"), "device", F.col("value").alias("latency"), F.to_date("ts").alias("day"))
