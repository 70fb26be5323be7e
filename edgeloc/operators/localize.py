"""Localization from series to a ranking: centralized, decentralized, and their variants."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeloc.operators import aggregate, birch, evaluate, exchange, metrics, ppr, scoring, subgraph
from edgeloc.sources.scenarios import Inputs
from edgeloc.sources.storage import checkpointed, small


@dataclass
class Scores:
    nodes: DataFrame  # scenario, node, s: services that an incident touches, scored over the whole graph
    edges: DataFrame  # scenario, src, dst, w: anomalous calls
    node_flags: DataFrame
    edge_flags: DataFrame
    parts: DataFrame | None = None  # scenario, node, src, s: what s is made of


@dataclass
class Result:
    final: DataFrame  # scenario, node, rank
    ranking: DataFrame
    decision: DataFrame | None = None
    cross: DataFrame | None = None
    means: DataFrame | None = None
    linked: DataFrame | None = None


def flags(inputs: Inputs, beta: float = birch.BETA, scale: str = "l2", only: str = "all", grouping: str = "flagged") -> tuple[DataFrame, DataFrame]:
    """Flagged node and edge series, written once; only="latency" looks at edges alone, the habit of web applications.

    grouping="cocluster" keeps of each entity's flagged series the largest group of like shape: the other reading of an anomalous cluster.
    """

    def on(df: DataFrame, keys: list[str]) -> DataFrame:
        if scale == "l2":
            out = birch.detect_batches(df, beta, "v", "l2").where("is_anomalous")
        else:
            out = birch.detect(df.withColumn("z", metrics.normalized(F.col("v"), scale)), beta, "z").where("is_anomalous").drop("z")
        return birch.cocluster(out, keys) if grouping == "cocluster" else out

    if inputs.series is None or grouping == "cocluster":
        nodes, edges = checkpointed(on(inputs.nodes, ["scenario", "node"])), checkpointed(on(inputs.edges, ["scenario", "src", "dst"]))
    else:  # one pass; few series are flagged
        both = checkpointed(on(inputs.series, []))
        own = lambda df: df.select(*(F.col(c).alias(c) for c in df.columns))  # noqa: E731  columns of their own: the two are joined later
        nodes, edges = own(both.where("dst is null").drop("dst").withColumnRenamed("src", "node")), own(both.where("dst is not null"))
    return (nodes.where(F.lit(False)) if only == "latency" else nodes), edges


def triggers(node_flags: DataFrame, edge_flags: DataFrame, device_flags: DataFrame | None = None) -> DataFrame:
    """(scenario, layers, n_flags): any flag at any layer opens an incident."""
    both = node_flags.select("scenario", F.lit("service").alias("layer")).union(edge_flags.select("scenario", F.lit("network")))
    if device_flags is not None:
        both = both.union(device_flags.select("scenario", F.lit("device")))
    return both.groupBy("scenario").agg(F.array_sort(F.collect_set("layer")).alias("layers"), F.count("*").alias("n_flags"))


def device_flags(inputs: Inputs, beta: float = birch.BETA) -> DataFrame:
    """Flagged series (scenario, device, metric) of devices: the sums of their services' metrics, bin by bin."""
    placed = inputs.nodes.join(inputs.services.select(F.col("service").alias("node"), "device"), "node")
    sums = placed.select("scenario", "device", "metric", F.posexplode("v").alias("t", "x")).groupBy("scenario", "device", "metric", "t").agg(F.sum("x").alias("x"))
    v = F.transform(F.array_sort(F.collect_list(F.struct("t", "x"))), lambda p: p["x"])
    return birch.detect_batches(sums.groupBy("scenario", "device", "metric").agg(v.alias("v")), beta, "v", "l2").where("is_anomalous")


def score(inputs: Inputs, beta: float = birch.BETA, pairs: str = "half", kind: str = "pearson", parts=("metric", "edge"), scoring_by: str = "metrics", only: str = "all", grouping: str = "flagged") -> Scores:
    """Scores of touched services and anomalous calls, checkpointed: every variant starts from them."""
    node_flags, edge_flags = flags(inputs, beta, only=only, grouping=grouping)
    if scoring_by == "rt":
        front = edge_flags.where("metric = 'p90'").select("scenario", "src", "dst", "v", F.element_at("v", -1).alias("last"))
        front = front.groupBy("scenario").agg(F.max_by("v", F.struct("last", "src", "dst")).alias("rt"))
        made = scoring.rt_scores(node_flags, front, ("scenario", "node"), "s", kind).select("scenario", "node", F.lit(None).cast("string").alias("src"), "s")
        es = scoring.rt_scores(edge_flags, front, ("scenario", "src", "dst"), "w", kind)
    else:
        made, es = scoring.score_parts(node_flags, edge_flags, pairs, kind, parts), scoring.edge_scores(edge_flags, pairs, kind)
    made = checkpointed(made)
    seen = node_flags.select("scenario", "node").union(edge_flags.select("scenario", "src")).union(edge_flags.select("scenario", "dst")).distinct()
    nodes = seen.join(made.groupBy("scenario", "node").agg(F.sum("s").alias("s")), ["scenario", "node"], "left").withColumn("s", F.coalesce("s", F.lit(0.0)))
    return Scores(checkpointed(nodes), checkpointed(es), node_flags, edge_flags, made)


def centralized(scores: Scores, alpha: float = 0.5, eps: float = 1e-6) -> Result:
    one = F.lit(-1).cast("long").alias("grp")
    r = checkpointed(ppr.solve_local(scores.nodes.select("*", one), scores.edges.select("*", one), alpha=alpha, eps=eps))
    return Result(r.select("scenario", "node", "rank"), r)


def decentralized(inputs: Inputs, scores: Scores, alpha: float = 0.5, eps: float = 1e-6, cluster_map: DataFrame | None = None, use_exchange: bool = True, aggregate_mode: str = "auto", renormalize: bool = False, rounds: int = 1, flagged_only: bool = False, scope: str = "subgraph", walk: DataFrame | None = None) -> Result:
    """Each cluster on its own subgraph, linked clusters after one exchange of mean scores (or more rounds, sending ranked mass), then one answer.

    cluster_map(device, cluster) serves all scenarios; with a column scenario each has its own. scope says whether a node's score may count callers that its
    subgraph doesn't have ("global"). walk(scenario, alpha, eps) gives scenarios walks of their own.
    """
    cmap = inputs.cluster_map if cluster_map is None else cluster_map
    keys = ("scenario",) if "scenario" in cmap.columns else ()
    own, calls = (checkpointed(x) for x in subgraph.form(inputs.services, inputs.calls, cmap, keys))
    of = own.where("not is_shadow").select(*keys, "node", F.col("cluster").cast("long").alias("cluster"))
    parts = scores.parts if scores.parts is not None else scores.nodes.select("scenario", "node", F.lit(None).cast("string").alias("src"), "s")
    nodes, inner, cross = subgraph.populate(small(own), small(calls), scores.nodes, parts, scores.edges, scope, keys)
    nodes, cross = checkpointed(nodes), checkpointed(cross if use_exchange else cross.where(F.lit(False)))
    means = exchange.mean_score(nodes, small(of), flagged_only, keys)
    linked = exchange.linked(cross)
    sent = means = checkpointed(means)
    for k in range(rounds):
        all_nodes, all_edges = exchange.augment(nodes, inner, cross, sent)
        all_nodes = all_nodes if walk is None else all_nodes.join(small(walk), "scenario")
        ranking = checkpointed(ppr.solve_local(all_nodes, all_edges, alpha=alpha, eps=eps))
        if k + 1 < rounds:  # what a cluster sends next is its own mean, weighed by the mass that it kept
            kept = aggregate.local_part(ranking).groupBy("scenario", F.col("grp").alias("cluster")).agg(F.sum("r").alias("kept"))
            sent = means.join(kept, ["scenario", "cluster"]).select("scenario", "cluster", (F.col("mean_s") * F.col("kept")).alias("mean_s"))
    decision = aggregate.decide(ranking, linked)
    mass = nodes.groupBy("scenario", "grp").agg(F.sum("s").alias("t"))
    final = aggregate.final_ranking(ranking, linked, decision, mass, renormalize, aggregate_mode)
    return Result(final.select("scenario", "node", "rank"), ranking, decision, cross, means, linked)


def compare(inputs: Inputs, central: Result, decentral: Result) -> DataFrame:
    """truth with propagation type, ranks and work of both runs."""
    c = evaluate.ranks(central.final, inputs.truth).withColumnRenamed("rank", "rank_c")
    d = evaluate.ranks(decentral.final, inputs.truth).select("scenario", F.col("rank").alias("rank_d"))
    t = exchange.propagation_type(inputs.truth, decentral.cross)
    wc, wd = evaluate.work(central.ranking), evaluate.work(decentral.ranking)
    return c.join(d, "scenario").join(t, "scenario").join(wc.select("scenario", F.col("t_max").alias("t_c")), "scenario", "left").join(wd.select("scenario", F.col("t_max").alias("t_d")), "scenario", "left")


COPY = 100_000  # more than there are scenarios


def replicated(scores: Scores, copies: int) -> Scores:
    """Scores once for each of some settings, so that one job runs them all: copy c of scenario s is scenario c * COPY + s."""

    def many(df: DataFrame) -> DataFrame:
        each = df.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
        return each.select(*((F.col("scenario") + COPY * F.col("copy")).cast("int").alias("scenario") if c == "scenario" else F.col(c) for c in df.columns))

    return Scores(many(scores.nodes), many(scores.edges), scores.node_flags, scores.edge_flags, None if scores.parts is None else many(scores.parts))


def copy_of(df: DataFrame) -> DataFrame:
    """df of replicated scenarios with the scenario itself and its copy."""
    return df.withColumn("copy", F.floor(F.col("scenario") / COPY).cast("int")).withColumn("scenario", (F.col("scenario") % COPY).cast("int"))


def cluster_copies(maps: list[DataFrame], truth: DataFrame) -> DataFrame:
    """(scenario, device, cluster) for replicated scenarios: copy k has the clusters of maps[k], each shared or with a scenario column."""
    out = None
    for k, m in enumerate(maps):
        told = m if "scenario" in m.columns else m.crossJoin(F.broadcast(truth.select("scenario")))  # devices by scenarios, both few
        one = told.select((F.col("scenario") + COPY * k).cast("int").alias("scenario"), "device", F.col("cluster").cast("long").alias("cluster"))
        out = one if out is None else out.union(one)
    return checkpointed(out)


def score_ready(scores: Scores, of: DataFrame | None = None) -> DataFrame:
    """(scenario, grp, t): correlations made for the scores of a group; of(node, cluster), or the whole graph as group -1."""
    n = scores.node_flags.groupBy("scenario", "node").agg(F.count("*").alias("metrics"))
    calls = scores.parts.where("src is not null").select("scenario", "node", "src")
    if of is not None:
        ends = calls.join(of.toDF("node", "grp"), "node").join(of.toDF("src", "from"), "src")
        calls, n = ends.where("grp = from"), n.join(of.toDF("node", "grp"), "node")
    else:
        n = n.withColumn("grp", F.lit(-1).cast("long"))
    n = n.join(calls.groupBy("scenario", "node").agg(F.count("*").alias("callers")), ["scenario", "node"], "left")
    return evaluate.score_work(n.withColumn("callers", F.coalesce("callers", F.lit(0))))
