"""Connected components of an edge table, without gathering edges anywhere.

Alternating large-star and small-star rounds (a published scheme for map-reduce systems): every
round is two aggregations and two joins over narrow rows, and ends in a reliable checkpoint.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed


def _rehang(sym: DataFrame, only_larger: bool) -> DataFrame:
    """Hang neighbours of each u below the smallest of u and its neighbours."""
    low = sym.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("m"))
    moved = sym.join(low, "u")
    if only_larger:
        out = moved.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = moved.select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
    return out.where("u <> v").distinct()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges(a, b) of longs -> (node, label): label is the smallest node reachable; nodes without an edge are absent.

    Self links, repeated and null ends are allowed; the first two change nothing, the last are no links.
    """
    e = checkpointed(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("a is not null and b is not null and a <> b").distinct())
    before = None
    for _ in range(max_rounds):
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        e = checkpointed(_rehang(_rehang(both, True).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")), False))
        now = e.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("label")).union(e.select("v", "v").distinct())
