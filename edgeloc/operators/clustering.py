"""Clusters of devices by call frequency.

Fusing adds weights, so every order of admissible merges ends in the same finest stable partition: all pairs above the threshold
may be contracted at once. merge_parallel does that on DataFrames; merge_greedy is the reference, one heaviest pair at a time, over a bounded weight table.
"""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MAX_DRIVER_PAIRS = 1_000_000


def initial(services: DataFrame) -> DataFrame:
    return services.select("device", F.col("device").alias("cluster")).distinct()


def weights(freq: DataFrame, services: DataFrame, cluster_map: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, c1, c2, w) with c1 < c2: call frequency between clusters, both directions together."""
    own = [k for k in keys if k in cluster_map.columns]
    of = services.join(cluster_map, "device").select(*own, "service", "cluster")
    ends = freq.join(of.toDF(*own, "src", "c_src"), [*own, "src"]).join(of.toDF(*own, "dst", "c_dst"), [*own, "dst"]).where("c_src <> c_dst")
    return ends.groupBy(*keys, F.least("c_src", "c_dst").alias("c1"), F.greatest("c_src", "c_dst").alias("c2")).agg(F.sum("freq").alias("w"))


def threshold(w: DataFrame, tau_rel: float) -> float:
    """A share of all weight between clusters."""
    return tau_rel * (w.agg(F.sum("w")).first()[0] or 0)


def _pairs(w: DataFrame) -> dict[tuple, float]:
    rows = w.limit(MAX_DRIVER_PAIRS + 1).collect()
    if len(rows) > MAX_DRIVER_PAIRS:
        raise ValueError("the weight table is too large for the driver; use merge_parallel")
    return {(r.c1, r.c2): r.w for r in rows}


def merge_greedy(w: DataFrame, cluster_map: DataFrame, tau: float, most: int | None = None) -> DataFrame:
    """(device, cluster) by fusing the heaviest pair while it weighs more than tau; ties by smallest ids.

    With most, pairs that would hold more of the first clusters than that stay apart.
    """
    left, into = _pairs(w), {}
    size: dict = defaultdict(lambda: 1)
    while left and (best := min(left, key=lambda p: (-left[p], p))) and left[best] > tau:
        keep, gone = min(best), max(best)
        if most is not None and size[keep] + size[gone] > most:
            del left[best]  # sizes only grow: it never fits again, unless more weight brings the pair back
            continue
        into[gone] = keep
        size[keep] += size[gone]
        fused: dict[tuple, float] = defaultdict(float)
        for (a, b), x in left.items():
            a, b = (keep if a == gone else a), (keep if b == gone else b)
            if a != b:
                fused[min(a, b), max(a, b)] += x
        left = fused
    def root(c):
        while c in into:
            c = into[c]
        return c
    moved = [(c, root(c)) for c in into]
    if not moved:
        return cluster_map
    kind = cluster_map.schema["cluster"].dataType.simpleString()
    told = cluster_map.sparkSession.createDataFrame(moved, f"cluster {kind}, root {kind}")
    return cluster_map.join(F.broadcast(told), "cluster", "left").select("device", F.coalesce("root", "cluster").alias("cluster"))


def merge_parallel(w: DataFrame, cluster_map: DataFrame, tau: float | None, max_rounds: int = 50, keys: tuple[str, ...] = ()) -> DataFrame:
    """As merge_greedy, contracting every pair above tau at once. A round hooks each cluster to its smallest neighbour, and fuses weights.

    w(keys, c1, c2, w) has a row for each pair of clusters: small beside the calls. With keys, cluster_map(keys, device, cluster), and each key is a graph of its own; all
    are merged together, so rounds are those of the slowest. tau None takes the threshold from a column tau of w, the same in all rows of a key.
    """
    from edgeloc.sources.storage import checkpointed

    keys, w = list(keys), w if tau is None else w.withColumn("tau", F.lit(float(tau)))
    heavy = checkpointed(w.where(F.col("w") > F.col("tau")))
    for _ in range(max_rounds):
        if heavy.isEmpty():
            return cluster_map
        both = heavy.select(*keys, "c1", "c2").union(heavy.select(*keys, "c2", "c1")).toDF(*keys, "c", "n")
        hook = both.groupBy(*keys, "c").agg(F.min("n").alias("n")).select(*keys, "c", F.least("c", "n").alias("to"))
        jump = checkpointed(hook.join(hook.toDF(*keys, "to", "up"), [*keys, "to"], "left").select(*keys, "c", F.coalesce("up", "to").alias("to")))
        cluster_map = checkpointed(cluster_map.join(jump.toDF(*keys, "cluster", "to"), [*keys, "cluster"], "left").select(*keys, "device", F.coalesce("to", "cluster").alias("cluster")))
        moved = w.join(jump.toDF(*keys, "c1", "a"), [*keys, "c1"], "left").join(jump.toDF(*keys, "c2", "b"), [*keys, "c2"], "left").select(*keys, F.coalesce("a", "c1").alias("a"), F.coalesce("b", "c2").alias("b"), "w", "tau").where("a <> b")
        w = checkpointed(moved.groupBy(*keys, F.least("a", "b").alias("c1"), F.greatest("a", "b").alias("c2")).agg(F.sum("w").alias("w"), F.first("tau").alias("tau")))
        heavy = w.where(F.col("w") > F.col("tau"))
    raise RuntimeError(f"clusters did not settle in {max_rounds} rounds")


def with_threshold(w: DataFrame, tau_rel: float, keys: tuple[str, ...]) -> DataFrame:
    """w with a column tau: a share of each key's weight."""
    return w.join(w.groupBy(*keys).agg((F.sum("w") * tau_rel).alias("tau")), list(keys))


def quality(freq: DataFrame, services: DataFrame, cluster_map: DataFrame) -> DataFrame:
    """(cluster, devices, services, intra, inter, ratio): sizes beside the cut ratio."""
    size = services.join(cluster_map, "device").groupBy("cluster").agg(F.countDistinct("device").alias("devices"), F.count("*").alias("services"))
    return size.join(cut_ratio(freq, services, cluster_map), "cluster", "left")


def is_stable(w: DataFrame, tau: float) -> bool:
    return w.where(F.col("w") > tau).isEmpty()


def validate(services: DataFrame, cluster_map: DataFrame) -> DataFrame:
    """Devices without a cluster, or in several."""
    n = services.select("device").distinct().join(cluster_map, "device", "left").groupBy("device").agg(F.countDistinct("cluster").alias("clusters"))
    return n.where("clusters <> 1")


def cut_ratio(freq: DataFrame, services: DataFrame, cluster_map: DataFrame) -> DataFrame:
    """(cluster, intra, inter, ratio): calls that leave a cluster's services, inside it or not."""
    of = services.join(cluster_map, "device").select("service", "cluster")
    ends = freq.join(of.toDF("src", "cluster"), "src").join(of.toDF("dst", "c_dst"), "dst")
    same = F.col("cluster") == F.col("c_dst")
    sums = ends.groupBy("cluster").agg(F.sum(F.when(same, F.col("freq")).otherwise(0)).alias("intra"), F.sum(F.when(~same, F.col("freq")).otherwise(0)).alias("inter"))
    return sums.withColumn("ratio", F.col("intra") / (F.col("intra") + F.col("inter")))
