"""Fault scenarios on the given tables: a stand-in for an injected-fault dataset. What is found on them says nothing about real systems.

Nations are services and devices. The graph and the faults are small tables made on the driver (25 services, 100 calls, 383 scenarios);
series are made in Spark, one packed array of 40 bins for each scenario, entity and metric.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgeloc.operators import clustering, topology
from edgeloc.sources.storage import checkpointed
from edgeloc.sources.tables import load, supplier_spans

NODE_METRICS = ("cpu", "mem", "io", "net_in", "net_out", "errors")
EDGE_METRICS = ("p50", "p90", "p99")
FAULTS = ("cpu", "memory", "latency", "loss", "duplication", "corruption", "disorder", "delay", "jitter")
SCENARIOS, HH, BINS, FROM_BIN = 383, 146, 40, 20
WINDOWS = 7  # of traces, each with a call graph of its own; prime to 128, so that each has calls across communities


@dataclass
class Inputs:
    services: DataFrame  # service, device
    calls: DataFrame  # src, dst, freq
    cluster_map: DataFrame  # device, cluster
    nodes: DataFrame  # scenario, node, metric, v
    edges: DataFrame  # scenario, src, dst, metric, v
    truth: DataFrame  # scenario, grp, fault, root
    series: DataFrame | None = None  # scenario, src, dst, metric, v: nodes (dst is null) and edges together, for one pass over both


def _thinned(spark: SparkSession, sf_dir: str) -> DataFrame:
    calls = topology.calls_from_traces(supplier_spans(spark, sf_dir, timed=False), carry=("device",), service="service")
    place = load(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("src"), F.col("s_nationkey").cast("long").alias("a"))
    return calls.join(place, "src").select("trace", "a", F.col("device").alias("b")).where("a <> b and (a % 3 = b % 3 or trace % 128 = 0)")


def thinned_nation_calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, freq) between nations: calls that stay in a community (nation mod 3), and those of every 128th order."""
    return _thinned(spark, sf_dir).groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.count("*").alias("freq"))


def window_calls(spark: SparkSession, sf_dir: str, windows: int = WINDOWS) -> DataFrame:
    """(window, src, dst, freq): the thinned calls of each window of traces (trace mod windows). Scenario s has the graph of window s mod windows."""
    return _thinned(spark, sf_dir).groupBy((F.col("trace") % windows).cast("int").alias("window"), F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.count("*").alias("freq"))


def window_clusters(spark: SparkSession, sf_dir: str, tau_rel: float = 0.01, windows: int = WINDOWS) -> DataFrame:
    """(window, device, cluster): each window's own clusters, all windows merged in one job."""
    devices = load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("service"), F.col("n_nationkey").cast("long").alias("device"))
    w = clustering.weights(window_calls(spark, sf_dir, windows), devices, clustering.initial(devices), ("window",))
    first = clustering.initial(devices).select(F.explode(F.sequence(F.lit(0), F.lit(windows - 1))).alias("window"), "device", "cluster")
    return clustering.merge_parallel(checkpointed(clustering.with_threshold(w, tau_rel, ("window",))), first, None, keys=("window",))


def scenario_clusters(spark: SparkSession, sf_dir: str, n_scenarios: int = SCENARIOS, tau_rel: float = 0.01) -> DataFrame:
    """(scenario, device, cluster): each scenario's clusters are those of its window of traces."""
    s = spark.range(n_scenarios).select(F.col("id").cast("int").alias("scenario"), (F.col("id") % WINDOWS).cast("int").alias("window"))
    return s.join(window_clusters(spark, sf_dir, tau_rel), "window").select("scenario", "device", "cluster")


def _graph(freq: DataFrame) -> list[tuple[int, int, int]]:
    """The three most called in the community and the most called outside, for each of the 25 nations."""
    by = defaultdict(list)
    for r in freq.collect():  # at most 25 x 24 rows
        by[r.src].append((-r.freq, r.dst))
    out = []
    for a in sorted(by):
        ordered = sorted(by[a])
        same = [x for x in ordered if x[1] % 3 == a % 3][:3]
        other = [x for x in ordered if x[1] % 3 != a % 3][:1]
        out += [(a, b, -f) for f, b in same + other]
    return out


def _impacts(graph, n_scenarios: int, crossing_every: int):
    """Scenarios, and factors of what their faults and the unrelated incidents touch."""
    callers, at = defaultdict(list), {(a, b): k for k, (a, b, _) in enumerate(graph)}
    for a, b, _ in graph:
        callers[b].append(a)
    truth, hit = [], []
    for s in range(n_scenarios):
        root, fault, may_cross = (11 * s + 5) % 25, s % 9, s % crossing_every == 0
        truth.append((s, "HH" if s < HH else "SH", FAULTS[fault], str(root)))
        factor, level = {root: (8.0, 4)}, [root]
        ways = {}
        for a, many in ((4.8, 3), (2.9, 2)):
            reached = []
            for b in level:
                for c in sorted(callers[b]):
                    if may_cross or c % 3 == b % 3:
                        ways.setdefault((c, b), a)
                        if c not in factor:
                            factor[c] = (a, many)
                            reached.append(c)
            level = reached
        for node, (a, many) in factor.items():
            hit += [(s, node, (fault + k + (0 if node == root else node)) % 6, a, 0.0) for k in range(many)]
        hit += [(s, 100 + at[w], m, a, 0.0) for w, a in ways.items() for m in range(3)]
        for q in (0, 1):
            node = (7 * s + 13 * q + 3) % 25
            if node not in factor:
                hit += [(s, node, (s + q + k) % 6, 0.0, 3.0) for k in range(3)]
    return truth, hit


def noise_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(at, u): for each of all events, in order of id, the BINS noise levels from it on, going round at the end."""
    value = load(spark, sf_dir, "events").select("event_id", "value")
    told = F.broadcast(value.agg(F.percentile("value", 0.95).alias("top"), F.count("*").alias("n")))  # one row
    part = checkpointed(value.sort("event_id", "value").select("value", F.spark_partition_id().alias("part"), (F.monotonically_increasing_id() % (1 << 33)).alias("k")))
    before = part.groupBy("part").agg(F.count("*").alias("m")).select("part", (F.sum("m").over(Window.orderBy("part")) - F.col("m")).alias("base"))  # one row for each partition
    level = part.join(F.broadcast(before), "part").withColumn("i", F.col("base") + F.col("k")).crossJoin(told)
    each = level.select("i", "n", (F.least("value", "top") / F.col("top")).alias("x"), F.explode(F.sequence(F.lit(0), F.lit(BINS - 1))).alias("t"))
    packed = each.groupBy(F.pmod(F.col("i") - F.col("t"), F.col("n")).cast("long").alias("at")).agg(F.array_sort(F.collect_list(F.struct("t", "x"))).alias("p"))
    return packed.select("at", F.transform("p", lambda p: p["x"]).alias("u"))


def build(spark: SparkSession, sf_dir: str, n_scenarios: int = SCENARIOS, noise: float = 1.0, crossing_every: int = 4, tau_rel: float = 0.01) -> Inputs:
    freq = checkpointed(thinned_nation_calls(spark, sf_dir))  # at most 25 x 24 rows, read several times
    services = load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("string").alias("service"), F.col("n_nationkey").cast("long").alias("device"))
    calls = freq.select(F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst"), "freq")
    first = clustering.initial(services)
    w = checkpointed(clustering.weights(calls, services, first))  # read for the threshold and for the merges
    cluster_map = clustering.merge_greedy(w, first, clustering.threshold(w, tau_rel))  # 25 devices
    graph = _graph(freq)
    truth, hit = _impacts(graph, n_scenarios, crossing_every)
    u = noise_windows(spark, sf_dir)
    n_events = load(spark, sf_dir, "events").count()
    entities = [(k, str(k), None, m, name) for k in range(25) for m, name in enumerate(NODE_METRICS)] + [(100 + k, str(a), str(b), m, name) for k, (a, b, _) in enumerate(graph) for m, name in enumerate(EDGE_METRICS)]
    grid = F.broadcast(spark.createDataFrame(entities, "e int, src string, dst string, j int, metric string"))
    touched = F.broadcast(spark.createDataFrame(hit, "scenario int, e int, j int, ramp double, square double").groupBy("scenario", "e", "j").agg(F.max("ramp").alias("ramp"), F.max("square").alias("square")))
    rows = spark.range(n_scenarios).select(F.col("id").cast("int").alias("scenario")).join(grid).join(touched, ["scenario", "e", "j"], "left")
    base = 7919 * F.col("scenario") + 131 * F.col("e") + 17 * F.col("j")
    rows = rows.withColumn("at", F.pmod(base.cast("long"), F.lit(n_events))).join(u, "at")
    ramp, square = F.coalesce("ramp", F.lit(0.0)), F.coalesce("square", F.lit(0.0))
    rise = lambda t: F.when(t >= FROM_BIN, ramp * (1 + (t % 5) / 5) + square * (F.floor(t / 5) % 2)).otherwise(0.0)
    v = F.transform(F.sequence(F.lit(0), F.lit(BINS - 1)), lambda t: (1 + noise * F.get("u", t)) * (1 + rise(t)))
    series = rows.select("scenario", "src", "dst", "metric", v.alias("v"))
    nodes = series.where("dst is null").select("scenario", F.col("src").alias("node"), "metric", "v")
    edges = series.where("dst is not null").select("scenario", "src", "dst", "metric", "v")
    told = spark.createDataFrame(truth, "scenario int, grp string, fault string, root string")
    return Inputs(services, calls, cluster_map, nodes, edges, told, series)
