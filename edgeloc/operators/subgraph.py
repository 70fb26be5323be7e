"""Self-contained subgraphs of clusters: own services, calls inside, and calls out to shadow nodes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def form(services: DataFrame, calls: DataFrame, cluster_map: DataFrame, keys: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """sub_nodes(cluster, node, is_shadow, remote_service, remote_cluster) and sub_edges(cluster, src, dst, freq, crosses, callee, callee_cluster).

    A call that crosses is kept in the caller's cluster only, and ends there in one shadow for each remote callee.
    With keys, cluster_map has them too (each scenario its own clusters); calls may have them, or serve all.
    """
    of = services.join(cluster_map, "device").select(*keys, F.col("service").cast("string").alias("service"), "cluster")
    own_keys = [k for k in keys if k in calls.columns]
    ends = calls.select(*own_keys, F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("callee"), "freq")
    ends = ends.join(of.toDF(*keys, "src", "cluster"), [*own_keys, "src"]).join(of.toDF(*keys, "callee", "callee_cluster"), [*keys, "callee"])
    crosses = F.col("cluster") != F.col("callee_cluster")
    edges = ends.select(*keys, "cluster", "src", F.when(crosses, F.concat(F.lit("shadow:"), "callee")).otherwise(F.col("callee")).alias("dst"), "freq", crosses.alias("crosses"), "callee", "callee_cluster")
    none = F.lit(None)
    own = of.select(*keys, "cluster", F.col("service").alias("node"), F.lit(False).alias("is_shadow"), none.cast("string").alias("remote_service"), none.cast(of.schema["cluster"].dataType).alias("remote_cluster"))
    shadows = edges.where("crosses").select(*keys, "cluster", F.col("dst").alias("node"), F.lit(True).alias("is_shadow"), F.col("callee").alias("remote_service"), F.col("callee_cluster").alias("remote_cluster")).distinct()
    return own.union(shadows), edges


def populate(sub_nodes: DataFrame, sub_edges: DataFrame, touched: DataFrame, parts: DataFrame, edge_scores: DataFrame, scope: str = "subgraph", keys: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The subgraphs at an incident: nodes(scenario, grp, node, s), inner edges(scenario, grp, src, dst, w), and
    crossing(scenario, cluster, src, callee, callee_cluster, w), the anomalous calls that end in a shadow.

    touched(scenario, node, s over the whole graph) says which own nodes take part, shadows never do. scope "subgraph" adds up only those parts that
    the cluster has: a node's own metrics and callers on calls inside; "global" takes the score over the whole graph.
    """
    own = sub_nodes.where("not is_shadow").select(*keys, F.col("cluster").cast("long").alias("grp"), "node")
    calls = sub_edges.select(*keys, F.col("cluster").cast("long").alias("grp"), "src", "callee", "crosses", F.col("callee_cluster").cast("long").alias("callee_cluster"))
    nodes = touched.join(own, [*keys, "node"])
    if scope == "subgraph":
        inside = calls.where("not crosses").select(*keys, "src", F.col("callee").alias("node"))
        local = parts.where("src is null").drop("src").unionByName(parts.where("src is not null").join(inside, [*keys, "src", "node"], "left_semi").drop("src"))
        nodes = nodes.drop("s").join(local.groupBy("scenario", "node").agg(F.sum("s").alias("s")), ["scenario", "node"], "left")
    met = edge_scores.withColumnRenamed("dst", "callee").join(calls, [*keys, "src", "callee"])
    inner = met.where("not crosses").select("scenario", "grp", "src", F.col("callee").alias("dst"), "w")
    crossing = met.where("crosses").select("scenario", F.col("grp").alias("cluster"), "src", "callee", "callee_cluster", "w")
    return nodes.select("scenario", "grp", "node", F.coalesce("s", F.lit(0.0)).alias("s")), inner, crossing


def two_way(edges: DataFrame) -> DataFrame:
    """(c1, c2): pairs of clusters that call each other, which the method isn't meant for."""
    out = edges.where("crosses").select("cluster", "callee_cluster").distinct()
    back = out.toDF("callee_cluster", "cluster").select("cluster", "callee_cluster")
    return out.intersect(back).where("cluster < callee_cluster").toDF("c1", "c2")
