"""Metric series of nodes and edges: long rows (entity, metric, t, value), or packed arrays (entity, metric, v)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PERCENTILES = (0.5, 0.9, 0.99)


def node_series(spans: DataFrame, bins: Column, node: str = "service", value: str = "latency", percentiles: tuple[float, ...] = PERCENTILES) -> DataFrame:
    """Count, mean, maximum and percentiles of value for each node and bin: one aggregation, then rows from its columns."""
    names = ["count", "avg", "max", *(f"p{round(p * 100)}" for p in percentiles)]
    aggs = [F.count("*").cast("double"), F.avg(value), F.max(value), *(F.percentile(value, p) for p in percentiles)]
    wide = spans.groupBy(F.col(node).alias("entity"), bins.alias("t")).agg(*(a.cast("double").alias(n) for a, n in zip(aggs, names)))
    return wide.unpivot(["entity", "t"], names, "metric", "value").select("entity", "metric", "t", "value")


def edge_series(calls: DataFrame, bins: Column, value: str = "latency", percentiles: tuple[float, ...] = PERCENTILES, accuracy: int | None = None) -> DataFrame:
    """Latency percentiles of each call edge and bin; exact, or approximate with a mergeable sketch where accuracy is given."""
    names = [f"p{round(p * 100)}" for p in percentiles]
    aggs = [F.percentile(value, p) if accuracy is None else F.percentile_approx(value, p, accuracy) for p in percentiles]
    wide = calls.groupBy("src", "dst", bins.alias("t")).agg(*(a.cast("double").alias(n) for a, n in zip(aggs, names)))
    return wide.unpivot(["src", "dst", "t"], names, "metric", "value")


def device_series(spans: DataFrame, bins: Column, attach: DataFrame | None = None, **how) -> DataFrame:
    """As node_series, of devices; with attach(service, device) a device's series is given to each service that it hosts."""
    s = node_series(spans, bins, node="device", **how)
    if attach is None:
        return s
    return s.withColumnRenamed("entity", "device").join(attach, "device").select(F.col("service").alias("entity"), F.concat(F.lit("device_"), "metric").alias("metric"), "t", "value")


def link_series(calls: DataFrame, place: DataFrame, bins: Column, **how) -> DataFrame:
    """As edge_series, of pairs of devices; place(service, device). Calls inside a device use no link."""
    ends = calls.join(place.toDF("src", "a"), "src").join(place.toDF("dst", "b"), "dst").where("a <> b")
    return edge_series(ends.drop("src", "dst").withColumnsRenamed({"a": "src", "b": "dst"}), bins, **how)


def align(series: DataFrame, first: int, last: int, how: str = "zero") -> DataFrame:
    """A value for every bin from first to last: missing ones are 0, or ("last") the last seen."""
    grid = series.select("entity", "metric").distinct().select("*", F.explode(F.sequence(F.lit(first), F.lit(last))).alias("t"))
    full = grid.join(series, ["entity", "metric", "t"], "left")
    if how == "last":
        w = Window.partitionBy("entity", "metric").orderBy("t")
        full = full.withColumn("value", F.last("value", ignorenulls=True).over(w))
    return full.withColumn("value", F.coalesce("value", F.lit(0.0)))


def pack(series: DataFrame) -> DataFrame:
    """(entity, metric, v): v is the values in order of bins; a series is as long as its bins are many."""
    both = F.array_sort(F.collect_list(F.struct("t", "value")))
    return series.groupBy("entity", "metric").agg(F.transform(both, lambda x: x["value"]).alias("v"))


def normalized(v: Column, how: str = "l2") -> Column:
    """An array scaled to unit length, to [0, 1], or to zero mean and unit deviation; constant ones become zeros but for l2."""
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    if how == "l2":
        size = F.sqrt(total(F.transform(v, lambda x: x * x)))
        scaled = F.transform(F.array(size), lambda n: F.transform(v, lambda x: F.when(n > 0, x / n).otherwise(0.0)))
        return F.get(scaled, 0)  # the norm is bound, so that it is taken once
    if how == "minmax":
        low, wide = F.array_min(v), F.array_max(v) - F.array_min(v)
        return F.transform(v, lambda x: F.when(wide > 0, (x - low) / wide).otherwise(0.0))
    mean = total(v) / F.size(v)
    dev = F.sqrt(total(F.transform(v, lambda x: (x - mean) * (x - mean))) / F.size(v))
    return F.transform(v, lambda x: F.when(dev > 0, (x - mean) / dev).otherwise(0.0))
