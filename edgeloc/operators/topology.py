"""Call graphs from traces, and placements of services on devices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from edgeloc.sources.storage import checkpointed


def calls_from_traces(spans: DataFrame, trace: str = "trace", pos: str = "pos", service: str = "service", carry: tuple[str, ...] = (), chunk: str | None = None) -> DataFrame:
    """(trace, src, dst, then the callee's carried columns): consecutive spans of different services. One shuffle, by trace.

    chunk names a column that never falls as pos rises in a trace (a day, say): a hot trace is then split by it, and the calls between
    chunks are made from the first and last span of each, of which there are few.
    """
    told = F.struct(F.col(service).alias("service"), *carry)
    by = [trace] if chunk is None else [trace, chunk]
    c = spans.select(trace, F.col(service).alias("src"), F.lead(told).over(Window.partitionBy(*by).orderBy(pos)).alias("n"))
    if chunk is not None:
        ends = spans.groupBy(trace, chunk).agg(F.min_by(told, pos).alias("first"), F.max_by(service, pos).alias("src"))
        c = c.union(ends.select(trace, "src", F.lead("first").over(Window.partitionBy(trace).orderBy(chunk)).alias("n")))
    return c.where(F.col("n.service") != F.col("src")).select(trace, "src", F.col("n.service").alias("dst"), *(F.col(f"n.{x}").alias(x) for x in carry))


def call_frequency(calls: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    return calls.groupBy(*keys, "src", "dst").agg(F.count("*").alias("freq"))


def dangling(services: DataFrame, calls: DataFrame) -> DataFrame:
    """Ends of calls that no service has."""
    return calls.select(F.col("src").alias("service")).union(calls.select("dst")).distinct().join(services, "service", "left_anti")


def graph(services: DataFrame, freq: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Vertices (node, kind) of services and devices, and the calls whose ends are services; dangling() names the ends of the others."""
    vertices = services.select(F.col("service").cast("string").alias("node"), F.lit("service").alias("kind")).union(services.select(F.col("device").cast("string"), F.lit("device")).distinct())
    known = services.select("service")
    return vertices, freq.join(known.toDF("src"), "src", "left_semi").join(known.toDF("dst"), "dst", "left_semi").select(*freq.columns)


def unlinked(services: DataFrame, calls: DataFrame) -> DataFrame:
    ends = calls.select(F.col("src").alias("service")).union(calls.select("dst"))
    return services.join(ends, "service", "left_anti")


def place_scattered(services: DataFrame, n: int, number: Column) -> DataFrame:
    """A control: services dealt to n devices by number."""
    return services.select("service", F.pmod(number, F.lit(n)).alias("device"))


def place_by_capacity(services: DataFrame, devices: DataFrame) -> DataFrame:
    """Services in order of id fill devices from the largest capacity down, in turns. Their numbers come from a range sort with counts of partitions, not from one task."""
    ranked = devices.select("device", (F.row_number().over(Window.orderBy(F.desc("capacity"), "device")) - 1).alias("slot"))  # devices are few
    n = devices.count()
    part = services.select("service").sort("service").withColumns({"part": F.spark_partition_id(), "i": F.monotonically_increasing_id() % (1 << 33)})
    part = checkpointed(part)
    before = part.groupBy("part").agg(F.count("*").alias("k")).select("part", (F.sum("k").over(Window.orderBy("part")) - F.col("k")).alias("base"))  # one row for each partition
    order = part.join(F.broadcast(before), "part").select("service", F.pmod(F.col("base") + F.col("i"), F.lit(n)).cast("int").alias("slot"))
    return order.join(F.broadcast(ranked), "slot").select("service", "device")


def place_by_communication(services: DataFrame, freq: DataFrame, n: int) -> DataFrame:
    """Frequent callers together: heaviest pairs fuse up to an even share of the services, and the groups are dealt to n devices, large ones first."""
    from edgeloc.operators import clustering

    alone = services.select("service", F.col("service").alias("device"))
    one = clustering.initial(alone)
    most = -(-services.count() // n)
    groups = clustering.merge_greedy(clustering.weights(freq, alone, one), one, 0, most).toDF("service", "group")
    sizes = groups.groupBy("group").agg(F.count("*").alias("k"))  # no more rows than services
    dealt = sizes.select("group", F.pmod(F.row_number().over(Window.orderBy(F.desc("k"), "group")) - 1, F.lit(n)).alias("device"))
    return groups.join(dealt, "group").select("service", "device")


def pick_host(devices: DataFrame, cluster_map: DataFrame) -> DataFrame:
    """(cluster, host): the device with the most capacity, the smallest of equals."""
    d = devices.join(cluster_map, "device")
    return d.groupBy("cluster").agg(F.max_by("device", F.struct("capacity", (-F.col("device")).alias("o"))).alias("host"))
