"""Anomaly scores of services and calls from flagged series, packed as arrays; no self join: pairs are made inside a row."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def _ranks(v: Column) -> Column:
    """Average ranks of the values of an array."""
    count = lambda f: _sum(F.transform(v, lambda y: f(y).cast("double")))
    return F.transform(v, lambda x: count(lambda y: y < x) + (count(lambda y: y == x) + 1) / 2)


def abs_corr(x: Column, y: Column, kind: str = "pearson") -> Column:
    """Direction-invariant correlation of two aligned arrays; 0 where it is undefined."""
    if kind == "spearman":
        return abs_corr(_ranks(x), _ranks(y))
    sums = ("n", "x", "y", "xx", "yy", "xy")
    zero = F.struct(*(F.lit(0.0).alias(k) for k in sums))

    def add(s, p):
        new = {"n": F.lit(1.0), "x": p["a"], "y": p["b"], "xx": p["a"] * p["a"], "yy": p["b"] * p["b"], "xy": p["a"] * p["b"]}
        return F.struct(*((s[k] + new[k]).alias(k) for k in sums))

    def told(s):
        sxx, syy, sxy = s["xx"] - s["x"] * s["x"] / s["n"], s["yy"] - s["y"] * s["y"] / s["n"], s["xy"] - s["x"] * s["y"] / s["n"]
        return F.when((sxx > 1e-12 * s["xx"]) & (syy > 1e-12 * s["yy"]), F.least(F.lit(1.0), F.abs(sxy) / F.sqrt(sxx * syy))).otherwise(0.0)

    r = F.aggregate(F.zip_with(x, y, lambda a, b: F.struct(a.alias("a"), b.alias("b"))), zero, add, told)
    return r * r if kind == "r2" else r


def pair_sum(vs: Column, pairs: str = "half", kind: str = "pearson") -> Column:
    """Sum of correlations over the pairs of an array of arrays: unordered, ordered ("full") or with self pairs ("self")."""
    rows = F.transform(vs, lambda x, i: _sum(F.transform(F.slice(vs, i + 2, F.size(vs)), lambda y: abs_corr(x, y, kind))))
    half = F.when(F.size(vs) > 0, _sum(rows)).otherwise(0.0)
    return half * 2 if pairs == "full" else half + F.size(vs) if pairs == "self" else half


def flagged_sets(flags: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """(keys, vs, metrics): the flagged series of each entity; an entity has few metrics."""
    two = F.array_sort(F.collect_list(F.struct("metric", "v")))
    return flags.where("is_anomalous").groupBy(*keys).agg(two.alias("m")).select(*keys, F.col("m.v").alias("vs"), F.col("m.metric").alias("metrics"))


def metric_score(flags: DataFrame, keys=("scenario", "node"), pairs: str = "half", kind: str = "pearson") -> DataFrame:
    return flagged_sets(flags, keys).select(*keys, pair_sum(F.col("vs"), pairs, kind).alias("s_metric"))


def call_influence(edge_flags: DataFrame, node_flags: DataFrame, kind: str = "pearson", latency: str = "p90") -> DataFrame:
    """(scenario, node, src, s): for each flagged caller edge the best match of its latency among the callee's flagged metrics."""
    rt = edge_flags.where((F.col("metric") == latency) & F.col("is_anomalous")).select("scenario", "src", F.col("dst").alias("node"), F.col("v").alias("rt"))
    best = F.array_max(F.transform("vs", lambda x: abs_corr(F.col("rt"), x, kind)))
    return rt.join(flagged_sets(node_flags, ("scenario", "node")), ["scenario", "node"]).select("scenario", "node", "src", best.alias("s"))


def edge_influence(edge_flags: DataFrame, node_flags: DataFrame, kind: str = "pearson", latency: str = "p90") -> DataFrame:
    """(scenario, node, s_edge): the influences of a node's callers, summed."""
    return call_influence(edge_flags, node_flags, kind, latency).groupBy("scenario", "node").agg(F.sum("s").alias("s_edge"))


def score_parts(node_flags: DataFrame, edge_flags: DataFrame, pairs: str = "half", kind: str = "pearson", parts=("metric", "edge")) -> DataFrame:
    """(scenario, node, src, s): what a node's score is made of. src is null for its own metrics, else the caller; a subgraph takes the callers that it has."""
    got = []
    if "metric" in parts:
        own = metric_score(node_flags, pairs=pairs, kind=kind)
        got.append(own.select("scenario", "node", F.lit(None).cast("string").alias("src"), F.col("s_metric").alias("s")))
    if "edge" in parts:
        got.append(call_influence(edge_flags, node_flags, kind))
    return reduce(DataFrame.unionByName, got)


def node_scores(node_flags: DataFrame, edge_flags: DataFrame, pairs: str = "half", kind: str = "pearson", parts=("metric", "edge")) -> DataFrame:
    """(scenario, node, s): the two influences added over the whole graph; an entity with either is there."""
    return score_parts(node_flags, edge_flags, pairs, kind, parts).groupBy("scenario", "node").agg(F.sum("s").alias("s"))


def edge_scores(edge_flags: DataFrame, pairs: str = "half", kind: str = "pearson") -> DataFrame:
    return metric_score(edge_flags, ("scenario", "src", "dst"), pairs, kind).withColumnRenamed("s_metric", "w")


def rt_scores(flags: DataFrame, front: DataFrame, keys: tuple[str, ...], out: str, kind: str = "pearson") -> DataFrame:
    """The cloud baseline: the best match of an entity's flagged series with the scenario's front-end latency (scenario, rt)."""
    best = F.max(abs_corr(F.col("v"), F.col("rt"), kind))
    return flags.where("is_anomalous").join(front, "scenario").groupBy(*keys).agg(best.alias(out))


def explain(flags: DataFrame, k: int = 3, keys=("scenario", "node"), calls: DataFrame | None = None) -> DataFrame:
    """(keys, a, b, corr): the k strongest terms of each entity's score: metric pairs, and with calls, as of call_influence, callers (a is then "call", b the caller)."""
    s = flagged_sets(flags, keys)
    pair = F.flatten(F.transform("vs", lambda x, i: F.transform(F.slice("vs", i + 2, F.size("vs")), lambda y, j: F.struct((-abs_corr(x, y)).alias("c"), F.get("metrics", i).alias("a"), F.get("metrics", i + j + 1).alias("b")))))
    terms = s.select(*keys, F.explode(F.slice(F.array_sort(pair), 1, k)).alias("p")).select(*keys, "p.a", "p.b", (-F.col("p.c")).alias("corr"))
    if calls is None:
        return terms
    both = terms.union(calls.select(*keys, F.lit("call"), "src", "s"))
    place = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc(F.round("corr", 12)), "a", "b"))
    return both.withColumn("place", place).where(F.col("place") <= k).drop("place")


def share(df: DataFrame, value: str, out: str, *by: str) -> DataFrame:
    """value as a share of its total over by: personalization and transition weights."""
    return df.withColumn(out, F.col(value) / F.sum(value).over(Window.partitionBy(*by)))
