"""Personalized PageRank: r = alpha (P^T r + dangling mass on s) + (1 - alpha) s, from caller to callee.

solve_local packs each group (a scenario's cluster) into one task and iterates there with no shuffle; a group is small by construction and guarded.
solve_relational iterates joins over large graphs, with edges dealt by source once; solve_steps takes a fixed number of steps.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgeloc.sources.storage import checkpointed

MAX_LOCAL_EDGES = 5_000_000


def iterate_groups(group: np.ndarray, s: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, alpha, eps, max_iter: int = 1000, dangling: str = "personalized", start: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The fixpoints of many graphs at once, and for each the steps taken and the last change; each graph stops by itself.

    group says which graph a node belongs to, from 0; src and dst are nodes. A node without outgoing weight gives its mass to s, itself ("loop") or none ("drop").
    start is a former result. alpha and eps are numbers, or arrays with one for each graph.
    """
    n, many = len(s), int(group.max(initial=-1)) + 1
    sums = lambda x: np.bincount(group, x, many)
    share = lambda x: np.divide(x, sums(x)[group], out=1 / np.bincount(group, minlength=many)[group], where=sums(x)[group] > 0)
    s = share(np.asarray(s, dtype=float))
    w = np.asarray(w, dtype=float)
    total = np.bincount(src, w, n).astype(float)  # integers if there are no edges
    p = np.divide(w, total[src], out=np.zeros_like(w, dtype=float), where=total[src] > 0)
    loose = total <= 0
    r = s.copy() if start is None else np.where(sums(start)[group] > 0, share(np.asarray(start, dtype=float)), s)
    keep = np.broadcast_to(np.asarray(alpha, dtype=float), many)[group]
    steps, change, going = np.zeros(many, dtype=int), np.zeros(many), np.ones(many, dtype=bool)
    for _ in range(max_iter):
        new = np.bincount(dst, p * r[src], n).astype(float)
        if dangling == "personalized":
            new += sums(np.where(loose, r, 0.0))[group] * s
        elif dangling == "loop":
            new[loose] += r[loose]
        new = keep * new + (1 - keep) * s
        if dangling == "drop":
            new /= sums(new)[group]
        far = sums(np.abs(new - r))
        r = np.where(going[group], new, r)
        steps += going
        change = np.where(going, far, change)
        going &= far >= eps
        if not going.any():
            break
    return r, steps, change


def iterate(s: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, alpha: float, eps: float, max_iter: int = 1000, dangling: str = "personalized", start: np.ndarray | None = None) -> tuple[np.ndarray, int, float]:
    """iterate_groups for one graph."""
    r, steps, change = iterate_groups(np.zeros(len(s), dtype=int), s, src, dst, w, alpha, eps, max_iter, dangling, start)
    return r, int(steps[0]), float(change[0])


def solve_local(nodes: DataFrame, edges: DataFrame, keys=("scenario", "grp"), alpha: float = 0.5, eps: float = 1e-6, max_iter: int = 1000, dangling: str = "personalized", max_edges: int | None = None) -> DataFrame:
    """nodes(keys, node, s), edges(keys, src, dst, w) -> (keys, node, r, rank, iterations, residual, n_nodes, n_edges). Edges with an end outside the group are left out.

    nodes may have a column r0, where the walk then starts, and alpha and eps, the same in all rows of a group, which take the place of the arguments.
    With max_edges, groups with more edges go to solve_relational instead: they are counted first. Without, a group above MAX_LOCAL_EDGES is an error.
    """
    keys = list(keys)
    if max_edges is not None:
        large = edges.groupBy(*keys).agg(F.count("*").alias("n_edges")).where(F.col("n_edges") > max_edges).select(*keys)
        large = checkpointed(large)
        if not large.isEmpty():
            near = solve_local(nodes.join(large, keys, "left_anti"), edges.join(large, keys, "left_anti"), keys, alpha, eps, max_iter, dangling)
            some = nodes.join(large, keys, "left_semi").select(*keys, F.col("node").cast("string").alias("node"), "s")
            ends = edges.join(large, keys, "left_semi").select(*keys, F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst"), "w")
            far = rank(solve_relational(some, ends, alpha, eps, keys=tuple(keys)), tuple(keys))
            count = lambda df, n: df.groupBy(*keys).agg(F.count("*").cast("int").alias(n))
            far = far.join(count(some, "n_nodes"), keys).join(count(ends, "n_edges"), keys)
            none = F.lit(None)
            return near.unionByName(far.select(*keys, "node", "r", "rank", none.cast("int").alias("iterations"), none.cast("double").alias("residual"), "n_nodes", "n_edges"))
    extra = [c for c in ("r0", "alpha", "eps") if c in nodes.columns]
    names = [*keys, "node", "r", "rank", "iterations", "residual", "n_nodes", "n_edges"]

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a):
            return pd.DataFrame({k: [] for k in names})
        a = a.sort_values([*keys, "node"], ignore_index=True)
        group = a.groupby(keys, sort=False, dropna=False).ngroup().to_numpy()
        place = a[[*keys, "node"]].assign(at=np.arange(len(a)))
        if not len(b):  # without the types of its columns
            b = place.head(0).rename(columns={"node": "src", "at": "w"}).assign(dst=place["node"].head(0))
        ends = b.merge(place.rename(columns={"node": "src"}), on=[*keys, "src"]).merge(place.rename(columns={"node": "dst"}), on=[*keys, "dst"], suffixes=("", "_dst"))
        src, dst = ends["at"].to_numpy(dtype=int), ends["at_dst"].to_numpy(dtype=int)
        n_nodes, n_edges = np.bincount(group), np.bincount(group[src], minlength=group[-1] + 1)
        if n_edges.max() > MAX_LOCAL_EDGES:
            raise ValueError("a group is too large for one task; give max_edges, or use solve_relational")
        first = np.flatnonzero(np.diff(group, prepend=-1))
        own = {c: a[c].to_numpy(dtype=float)[first] if c in extra else given for c, given in (("alpha", alpha), ("eps", eps))}
        start = a["r0"].fillna(0).to_numpy(dtype=float) if "r0" in extra else None
        r, steps, change = iterate_groups(group, a["s"].to_numpy(dtype=float), src, dst, ends["w"].to_numpy(dtype=float), own["alpha"], own["eps"], max_iter, dangling, start)
        order = np.lexsort((np.arange(len(r)), -r.round(12), group))
        rank = np.empty(len(r), dtype=int)
        rank[order] = np.arange(len(r)) - first[group] + 1
        return a[[*keys, "node"]].assign(r=r, rank=rank, iterations=steps[group], residual=change[group], n_nodes=n_nodes[group], n_edges=n_edges[group])

    kinds = dict(nodes.dtypes)
    schema = ", ".join(f"{k} {kinds[k]}" for k in keys) + ", node string, r double, rank int, iterations int, residual double, n_nodes int, n_edges int"
    # groups of a bucket are one call: small graphs are many, and walk side by side
    bucket = F.pmod(F.xxhash64(*keys), F.lit(4 * int(nodes.sparkSession.conf.get("spark.sql.shuffle.partitions")))).alias("bucket")
    own = [F.col(k).alias(k) for k in keys]  # columns of their own on both sides: edges and nodes may come of the same frame
    a = nodes.select(*own, F.col("node").cast("string").alias("node"), F.col("s").cast("double").alias("s"), *extra, bucket)
    b = edges.select(*own, F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst"), F.col("w").cast("double").alias("w"), bucket)
    return a.groupBy("bucket").cogroup(b.groupBy("bucket")).applyInPandas(run, schema)


def with_back_edges(edges: DataFrame, rho: float, keys=("scenario",)) -> DataFrame:
    """edges and their reverse at rho times the weight, as many localizers add: an extra, off elsewhere."""
    back = edges.select(*keys, F.col("dst").alias("src"), F.col("src").alias("dst"), (F.col("w") * rho).alias("w"))
    return edges.select(*keys, "src", "dst", "w").union(back).groupBy(*keys, "src", "dst").agg(F.sum("w").alias("w"))


def with_self_edges(nodes: DataFrame, edges: DataFrame, share: float, keys=("scenario",)) -> DataFrame:
    """edges and, for each node, one to itself of share times its own score."""
    own = nodes.select(*keys, F.col("node").alias("src"), F.col("node").alias("dst"), (F.col("s") * share).alias("w"))
    return edges.select(*keys, "src", "dst", "w").union(own.where("w > 0"))


def _step(r: DataFrame, p: DataFrame, s: DataFrame, alpha: float, keys: list[str]) -> DataFrame:
    """One step: mass along edges, and what dangling nodes hold onto s."""
    sent = r.withColumnRenamed("node", "src").join(p, [*keys, "src"], "left")
    moved = sent.where("dst is not null").groupBy(*keys, F.col("dst").alias("node")).agg(F.sum(F.col("r") * F.col("p")).alias("m"))
    loose = sent.where("dst is null").groupBy(*keys).agg(F.sum("r").alias("loose"))
    to = s.join(moved, [*keys, "node"], "left")
    to = to.join(loose, keys, "left") if keys else to.crossJoin(F.broadcast(sent.agg(F.sum(F.when(F.col("dst").isNull(), F.col("r"))).alias("loose"))))  # one row
    mass = F.coalesce("m", F.lit(0.0)) + F.coalesce("loose", F.lit(0.0)) * F.col("s")
    return to.select(*keys, "node", (F.lit(alpha) * mass + (1 - alpha) * F.col("s")).alias("r"))


def _prepared(nodes: DataFrame, edges: DataFrame, keys: list[str]) -> tuple[DataFrame, DataFrame]:
    """Shares of each graph; by sums, not by a window over all rows. Edges with an end outside the nodes are left out."""
    total = nodes.groupBy(*keys).agg(F.sum("s").alias("t"), F.count("*").alias("n"))
    s = (nodes.join(total, keys) if keys else nodes.crossJoin(F.broadcast(total))).select(*keys, "node", F.when(F.col("t") > 0, F.col("s") / F.col("t")).otherwise(1 / F.col("n")).alias("s"))
    known = nodes.select(*keys, "node")
    ends = edges.join(known.withColumnRenamed("node", "src"), [*keys, "src"], "left_semi").join(known.withColumnRenamed("node", "dst"), [*keys, "dst"], "left_semi")
    out = ends.groupBy(*keys, "src").agg(F.sum("w").alias("t")).where("t > 0")
    return s, ends.join(out, [*keys, "src"]).select(*keys, "src", "dst", (F.col("w") / F.col("t")).alias("p"))


class _Graph:
    """s and p of a walk: written once, then held in memory dealt by the node that a step reads, so that edges don't move again."""

    def __init__(self, nodes: DataFrame, edges: DataFrame, keys: tuple[str, ...]):
        self.keys = list(keys)
        s, p = (checkpointed(x) for x in _prepared(nodes, edges, self.keys))
        self.s, self.p = s.repartition(*self.keys, "node").persist(), p.repartition(*self.keys, "src").persist()

    def step(self, r: DataFrame, alpha: float) -> DataFrame:
        return checkpointed(_step(r, self.p, self.s, alpha, self.keys))

    def close(self) -> None:
        self.s.unpersist()
        self.p.unpersist()


def solve_relational(nodes: DataFrame, edges: DataFrame, alpha: float = 0.5, eps: float = 1e-6, max_iter: int = 200, check_every: int = 5, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, node, r) of graphs too large for a task; lineage is cut every step, and convergence (of the slowest graph) looked at every few."""
    g = _Graph(nodes, edges, keys)
    r = g.s.withColumnRenamed("s", "r")
    for _ in range(0, max_iter, check_every):
        before = r
        for _ in range(check_every):
            before, r = r, g.step(r, alpha)
        far = r.join(before.withColumnRenamed("r", "old"), [*keys, "node"]).groupBy(*keys).agg(F.sum(F.abs(F.col("r") - F.col("old"))).alias("d")).agg(F.max("d"))
        if (far.first()[0] or 0.0) < eps:
            break
    g.close()
    return r


def solve_steps(nodes: DataFrame, edges: DataFrame, alpha: float = 0.5, steps: int = 10, keys: tuple[str, ...] = ()) -> DataFrame:
    """A step reads the last vector twice, so it is written each time: the plan would double with every step."""
    g = _Graph(nodes, edges, keys)
    r = g.s.withColumnRenamed("s", "r")
    for _ in range(steps):
        r = g.step(r, alpha)
    g.close()
    return r


def rank(r: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    return r.withColumn("rank", F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc(F.round("r", 12)), "node")))
