"""What a user of SQL sees: views of every step, functions, a table function that traces a walk, and messages as JSON and maps."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgeloc.operators import localize, ppr, subgraph
from edgeloc.sources.scenarios import Inputs

FUNCTIONS = {
    "feature_radius(n DOUBLE, ls DOUBLE, ss DOUBLE) RETURNS DOUBLE": "sqrt(greatest(0.0D, ss / n - (ls / n) * (ls / n)))",
    "node_kind(node STRING) RETURNS STRING": "CASE WHEN startswith(node, 'shadow:') THEN 'shadow' WHEN startswith(node, 'cluster:') THEN 'cluster' ELSE 'service' END",
    "time_reduction(central DOUBLE, decentral DOUBLE) RETURNS DOUBLE": "(central - decentral) / central * 100",
}


class WalkSteps:
    """(step, node, r) of a walk from arrays: to follow small graphs, not to solve large ones."""

    def eval(self, nodes: list[str], s: list[float], src: list[str], dst: list[str], w: list[float], alpha: float, steps: int):
        at = {n: k for k, n in enumerate(nodes)}
        ends = np.array([at[x] for x in src], dtype=int), np.array([at[x] for x in dst], dtype=int)
        r = None
        for step in range(1, steps + 1):
            r, _, _ = ppr.iterate(np.array(s), *ends, np.array(w), alpha, 0.0, 1, start=r)
            for n, x in zip(nodes, r.tolist()):
                yield step, n, x


def register(spark: SparkSession) -> None:
    """The functions of FUNCTIONS, and walk_steps(nodes, s, src, dst, w, alpha, steps) as a table function."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("walk_steps", F.udtf(WalkSteps, returnType="step int, node string, r double"))


def views(inputs: Inputs, scores: localize.Scores, result: localize.Result) -> dict[str, DataFrame]:
    """Temporary views services, calls, clusters, subgraph_nodes, subgraph_edges, series, flags, scores and rankings; scenarios may be many, all views hold all."""
    own, edges = subgraph.form(inputs.services, inputs.calls, inputs.cluster_map)
    entity = lambda df: df.select("scenario", F.concat_ws(">", "src", "dst").alias("entity"), "metric", "v")
    both = lambda a, b: a.select("scenario", F.col("node").alias("entity"), "metric", "v").union(entity(b))
    out = {
        "services": inputs.services, "calls": inputs.calls, "clusters": inputs.cluster_map, "subgraph_nodes": own, "subgraph_edges": edges,
        "series": both(inputs.nodes, inputs.edges), "flags": both(scores.node_flags, scores.edge_flags), "scores": scores.nodes, "rankings": result.ranking,
    }
    for name, df in out.items():
        df.createOrReplaceTempView(name)
    return out


def message_json(messages: DataFrame) -> DataFrame:
    """(scenario, from_cluster, to_cluster, body): messages as they would go over a wire."""
    return messages.select("scenario", "from_cluster", "to_cluster", F.to_json(F.struct("kind", "mean_s", "crossing_w")).alias("body"))


def ranking_maps(ranking: DataFrame) -> DataFrame:
    """(scenario, grp, r): each group's ranking vector as a map, what clusters send when they disagree."""
    return ranking.groupBy("scenario", "grp").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("node", "r")))).alias("r"))


def volume(series: DataFrame, rsd: float = 0.02) -> DataFrame:
    """(entities, metrics, rows): about how many entities are monitored, with a relative error of rsd, and exactly how many rows."""
    return series.agg(F.approx_count_distinct("entity", rsd).alias("entities"), F.countDistinct("metric").alias("metrics"), F.count("*").alias("rows"))
