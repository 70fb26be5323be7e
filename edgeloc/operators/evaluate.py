"""Accuracy and cost of localization."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KS = (1, 2, 3, 5, 10)


def ranks(final: DataFrame, truth: DataFrame) -> DataFrame:
    """truth plus the rank of its root; one that isn't ranked comes after all that are."""
    many = final.groupBy("scenario").agg(F.count("*").alias("n"))
    hit = truth.join(final.select("scenario", F.col("node").alias("root"), "rank"), ["scenario", "root"], "left").join(many, "scenario", "left")
    return hit.withColumn("rank", F.coalesce("rank", F.coalesce("n", F.lit(0)) + 1)).drop("n")


def accuracy() -> list[Column]:
    """acc_k, mar and mrr of rank, as aggregates."""
    return [*(F.avg((F.col("rank") <= k).cast("double")).alias(f"acc_{k}") for k in KS), F.avg("rank").alias("mar"), F.avg(1 / F.col("rank")).alias("mrr")]


def reductions(central: str = "t_c", decentral: str = "t_d") -> list[Column]:
    """Mean of the scenarios' percentages, and the percentage of the sums."""
    c, d = F.col(central), F.col(decentral)
    return [F.avg((c - d) / c * 100).alias("avg_reduction"), ((F.sum(c) - F.sum(d)) / F.sum(c) * 100).alias("total_reduction")]


def work(ranking: DataFrame) -> DataFrame:
    """(scenario, t_max, t_sum): steps times nodes and edges, of the slowest group and of all."""
    g = ranking.select("scenario", "grp", (F.col("iterations") * (F.col("n_nodes") + F.col("n_edges"))).cast("double").alias("v")).distinct()
    return g.groupBy("scenario").agg(F.max("v").alias("t_max"), F.sum("v").alias("t_sum"))


def conflict_rate(decision: DataFrame) -> DataFrame:
    return decision.agg(F.avg((F.col("mode") != "consensus").cast("double")).alias("conflict_rate"), F.count("*").alias("multi"))


def communication(messages: DataFrame, series: DataFrame, bins: int) -> DataFrame:
    """Messages and bytes exchanged, and bytes that a central collector would move, eight for each number."""
    m = messages.agg(F.count("*").alias("messages"), F.sum((F.col("mean_s").isNotNull().cast("int") + F.col("crossing_w").isNotNull().cast("int")) * 8).alias("exchanged_bytes"))
    return m.join(series.agg((F.count("*") * bins * 8).alias("central_bytes")))


def score_work(parts_of: DataFrame) -> DataFrame:
    """(scenario, grp, t): correlations made for a group's scores: a pair for every two flagged metrics of a node, and one for each caller and metric; parts_of(scenario, grp, node, metrics, callers)."""
    k = F.col("metrics")
    return parts_of.groupBy("scenario", "grp").agg(F.sum(k * (k - 1) / 2 + k * F.col("callers")).cast("double").alias("t"))


def parallel_time(ranking: DataFrame, ready: DataFrame, pairs: DataFrame) -> DataFrame:
    """(scenario, t, total): time of an incident where groups run side by side: each starts its walk when its own scores, and those of linked groups, are there; the slowest ends it.

    ready(scenario, grp, t): when a group's scores are made; pairs(scenario, c1, c2, ready) of exchange.timeline. total is the sum of all groups' work.
    """
    walk = ranking.select("scenario", "grp", (F.col("iterations") * (F.col("n_nodes") + F.col("n_edges"))).cast("double").alias("walk")).distinct()
    met = pairs.select("scenario", F.explode(F.array("c1", "c2")).alias("grp"), "ready").groupBy("scenario", "grp").agg(F.max("ready").alias("met"))
    each = walk.join(ready, ["scenario", "grp"], "left").join(met, ["scenario", "grp"], "left").withColumn("t", F.coalesce("t", F.lit(0.0)))
    return each.groupBy("scenario").agg(F.max(F.greatest("t", F.coalesce("met", F.lit(0.0))) + F.col("walk")).alias("t"), F.sum(F.col("t") + F.col("walk")).alias("total"))


def clusters_per_scenario(cluster_map: DataFrame) -> DataFrame:
    """(clusters, scenarios): in how many scenarios there are so many clusters; cluster_map(scenario, device, cluster)."""
    n = cluster_map.groupBy("scenario").agg(F.countDistinct("cluster").alias("clusters"))
    return n.groupBy("clusters").agg(F.count("*").alias("scenarios"))
