"""From the clusters' rankings to one answer: consensus, or combined perspectives."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def with_kind(ranking: DataFrame) -> DataFrame:
    """kind is cluster for nodes that stand for another cluster, service for the rest."""
    return ranking.withColumn("kind", F.when(F.col("node").startswith("cluster:"), "cluster").otherwise("service"))


def decide(ranking: DataFrame, linked: DataFrame) -> DataFrame:
    """(scenario, mode, winner): consensus if one linked cluster alone names a service of its own, and the others point to it."""
    top = with_kind(ranking).where("rank = 1").join(linked.select("scenario", "grp").distinct(), ["scenario", "grp"])
    local = F.col("kind") == "service"
    by = top.groupBy("scenario").agg(F.sum(local.cast("int")).alias("locals"), F.max(F.when(local, F.col("grp"))).alias("w"), F.collect_set(F.when(~local, F.col("node"))).alias("to"))
    points = F.forall("to", lambda x: x == F.concat(F.lit("cluster:"), F.col("w").cast("string")))
    agreed = (F.col("locals") == 1) & points
    return by.select("scenario", F.when(agreed, "consensus").when(F.col("locals") > 1, "conflict").otherwise("pointing").alias("mode"), F.when(agreed, F.col("w")).alias("winner"))


def local_part(ranking: DataFrame, renormalize: bool = False) -> DataFrame:
    own = with_kind(ranking).where("kind = 'service'").select("scenario", "grp", "node", "r")
    return own.withColumn("r", F.col("r") / F.sum("r").over(Window.partitionBy("scenario", "grp"))) if renormalize else own


def influence(ranking: DataFrame, linked: DataFrame, renormalize: bool = False) -> DataFrame:
    """(scenario, seen_by, node, r): the mass that a cluster gives another, spread over that one's own part."""
    part = local_part(ranking, renormalize).join(linked.select("scenario", "grp").distinct(), ["scenario", "grp"])
    part = part.select("scenario", F.col("grp").cast("string").alias("to"), "node", "r")
    given = with_kind(ranking).where("kind = 'cluster'").select("scenario", F.col("grp").alias("seen_by"), F.substring_index("node", ":", -1).alias("to"), F.col("r").alias("mass"))
    return part.join(given, ["scenario", "to"]).select("scenario", "seen_by", "node", (F.col("mass") * F.col("r")).alias("r"))


def combine(ranking: DataFrame, linked: DataFrame, renormalize: bool = False) -> DataFrame:
    """(scenario, node, score): each linked cluster's own part and, spread over the others' own parts, the mass it gives them; their mean."""
    who = linked.select("scenario", "grp").distinct()
    own = local_part(ranking).join(who, ["scenario", "grp"])
    seen = influence(ranking, linked, renormalize).select("scenario", "node", "r")
    n = who.groupBy("scenario").agg(F.count("*").alias("n"))
    return own.select("scenario", "node", "r").union(seen).groupBy("scenario", "node").agg(F.sum("r").alias("r")).join(n, "scenario").select("scenario", "node", (F.col("r") / F.col("n")).alias("score"))


def merge_unlinked(ranking: DataFrame, mass: DataFrame) -> DataFrame:
    """(scenario, node, score): a cluster's own ranking times its share of the scenario's score; mass(scenario, grp, t)."""
    total = F.sum("t").over(Window.partitionBy("scenario"))
    share = mass.select("scenario", "grp", F.when(total > 0, F.col("t") / total).otherwise(F.lit(1.0)).alias("share"))
    return local_part(ranking).join(share, ["scenario", "grp"]).select("scenario", "grp", "node", (F.col("r") * F.col("share")).alias("score"))


def final_ranking(ranking: DataFrame, linked: DataFrame, decision: DataFrame, mass: DataFrame, renormalize: bool = False, mode: str = "auto") -> DataFrame:
    """(scenario, node, tier, score, rank): the winner's own order under consensus, then combined scores, then clusters that took no part.

    mode "always" combines in every linked scenario, "consensus" never does: without a winner each cluster's own order stands, by its share of the scores.
    """
    base = merge_unlinked(ranking, mass)
    both = base.join(combine(ranking, linked, renormalize).withColumnRenamed("score", "combined"), ["scenario", "node"], "left").join(decision, "scenario", "left")
    wins = F.lit(False) if mode == "always" else F.coalesce(F.col("grp") == F.col("winner"), F.lit(False))
    tier = F.when(wins, 0).when(F.col("combined").isNotNull() & F.lit(mode != "consensus"), 1).otherwise(2)
    score = F.when(tier == 1, F.col("combined")).otherwise(F.col("score"))
    out = both.select("scenario", "node", tier.alias("tier"), score.alias("score"))
    return out.withColumn("rank", F.row_number().over(Window.partitionBy("scenario").orderBy("tier", F.desc(F.round("score", 12)), "node")))
