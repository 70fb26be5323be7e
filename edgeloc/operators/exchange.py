"""Exchange between clusters that an anomalous call links: one mean score each, and the call's own score."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def crossings(edge_scores: DataFrame, of: DataFrame) -> DataFrame:
    """(scenario, cluster, src, callee, callee_cluster, w) of anomalous calls that leave their cluster; of(node, cluster)."""
    e = edge_scores.join(of.toDF("src", "cluster"), "src").join(of.toDF("dst", "callee_cluster"), "dst")
    return e.where("cluster <> callee_cluster").select("scenario", "cluster", "src", F.col("dst").alias("callee"), "callee_cluster", "w")


def propagation_type(scenarios: DataFrame, cross: DataFrame) -> DataFrame:
    hit = cross.select("scenario").distinct().withColumn("x", F.lit(True))
    return scenarios.select("scenario").join(hit, "scenario", "left").select("scenario", F.when(F.col("x"), "multi").otherwise("single").alias("type"))


def mean_score(nodes: DataFrame, of: DataFrame, flagged_only: bool = False, keys: tuple[str, ...] = ()) -> DataFrame:
    """(scenario, cluster, mean_s) of unnormalized scores over all services of the cluster, or over those with one; of(keys, node, cluster)."""
    sums = nodes.groupBy("scenario", F.col("grp").alias("cluster")).agg(F.sum("s").alias("t"), F.count("*").alias("k"))
    size = of.groupBy(*keys, "cluster").agg(F.count("*").alias("n"))
    return sums.join(size, [*keys, "cluster"]).select("scenario", "cluster", (F.col("t") / F.col("k" if flagged_only else "n")).alias("mean_s"))


def augment(nodes: DataFrame, edges: DataFrame, cross: DataFrame, means: DataFrame) -> tuple[DataFrame, DataFrame]:
    """nodes and edges with each linked cluster as one node, on both sides; several calls between two clusters add up."""
    name = lambda c: F.concat(F.lit("cluster:"), F.col(c).cast("string"))
    out = cross.groupBy("scenario", "cluster", "callee_cluster", "src").agg(F.sum("w").alias("w"))
    into = cross.groupBy("scenario", "cluster", "callee_cluster", "callee").agg(F.sum("w").alias("w"))
    more = out.select("scenario", F.col("cluster").alias("grp"), "src", name("callee_cluster").alias("dst"), "w").union(into.select("scenario", F.col("callee_cluster").alias("grp"), name("cluster").alias("src"), F.col("callee").alias("dst"), "w"))
    links = linked(cross)
    met = links.join(means.toDF("scenario", "other", "s"), ["scenario", "other"], "left").select("scenario", "grp", name("other").alias("node"), F.coalesce("s", F.lit(0.0)).alias("s"))
    return nodes.select("scenario", "grp", "node", "s").union(met), edges.select("scenario", "grp", "src", "dst", "w").union(more)


def linked(cross: DataFrame) -> DataFrame:
    """(scenario, grp, other), both ways."""
    a = cross.select("scenario", F.col("cluster").alias("grp"), F.col("callee_cluster").alias("other"))
    return a.union(a.select("scenario", "other", "grp")).distinct()


def messages(cross: DataFrame, means: DataFrame) -> DataFrame:
    """A wait message from each linked pair's caller side, and a score message each way."""
    pair = cross.groupBy("scenario", "cluster", "callee_cluster").agg(F.sum("w").alias("w"))
    log = pair.select("scenario", F.least("cluster", "callee_cluster").alias("a"), F.greatest("cluster", "callee_cluster").alias("b"), F.col("cluster").alias("caller"), "w").groupBy("scenario", "a", "b").agg(F.min("caller").alias("caller"), F.sum("w").alias("w"))
    other = F.when(F.col("caller") == F.col("a"), F.col("b")).otherwise(F.col("a"))
    rows = F.array(*(F.struct(f.alias("from_cluster"), t.alias("to_cluster"), F.lit(k).alias("kind")) for f, t, k in ((F.col("caller"), other, "wait"), (F.col("caller"), other, "score"), (other, F.col("caller"), "score"))))
    flat = log.select("scenario", "w", "caller", F.explode(rows).alias("m")).select("scenario", "m.*", "w", "caller")
    payload = F.when(F.col("kind") == "score", F.coalesce("mean_s", F.lit(0.0)))
    crossing = F.when((F.col("kind") == "score") & (F.col("from_cluster") == F.col("caller")), F.col("w"))
    return flat.join(means.toDF("scenario", "from_cluster", "mean_s"), ["scenario", "from_cluster"], "left").select("scenario", "from_cluster", "to_cluster", "kind", payload.alias("mean_s"), crossing.alias("crossing_w"))


def timeline(links: DataFrame, ready: DataFrame, notice: float = 0.0, delay: float = 0.0) -> DataFrame:
    """(scenario, c1, c2, wait_sent, wait_received, ready, idle) of each linked pair; ready(scenario, cluster, t) says when a cluster knows its own scores.

    All start at 0. notice is when a caller's cluster sees the anomalous crossing and sends its wait message, delay how long any message takes. Both scores
    are there at ready, the later one's time plus delay; the earlier cluster idles for the difference, whatever the delay, which both bear.
    """
    p = links.where("grp < other").toDF("scenario", "c1", "c2").join(ready.toDF("scenario", "c1", "t1"), ["scenario", "c1"]).join(ready.toDF("scenario", "c2", "t2"), ["scenario", "c2"])
    sent = F.lit(float(notice))
    return p.select("scenario", "c1", "c2", sent.alias("wait_sent"), (sent + delay).alias("wait_received"), (F.greatest("t1", "t2") + delay).alias("ready"), F.abs(F.col("t1") - F.col("t2")).alias("idle"))


def two_way_warning(crossing: DataFrame) -> DataFrame:
    """(scenario, c1, c2): pairs of clusters with anomalous calls both ways, frequent traffic of which the method isn't made for. It runs, with both roles for each."""
    one = crossing.select("scenario", F.col("cluster").alias("c1"), F.col("callee_cluster").alias("c2")).distinct()
    return one.where("c1 < c2").join(one.toDF("scenario", "c2", "c1"), ["scenario", "c1", "c2"], "left_semi")
