import numpy as np
import pytest
from pyspark.sql import functions as F

from edgeloc.operators import aggregate, baselines, birch, clustering, evaluate, localize, ppr, scoring, subgraph, topology


def test_features_of_hand_series(spark):
    df = spark.createDataFrame([("a", [0.0, 0.02, 0.03, 0.5]), ("b", [0.0, 0.02, 0.03]), ("c", [1.0] * 5)], "k string, v array<double>")
    assert dict(birch.detect(df).select("k", "n_features").collect()) == {"a": 2, "b": 1, "c": 1}


def test_batches_and_tree_equal_the_fold(spark):
    x = np.random.default_rng(1).normal(0, 0.1, (20, 30))
    df = spark.createDataFrame([(k, r.tolist()) for k, r in enumerate(x)], "k int, v array<double>")
    fold = dict(birch.detect(df).select("k", "n_features").collect())
    assert fold == dict(enumerate(birch.count_features(x).tolist())) == dict(birch.detect_tree(df).select("k", "n_features").collect())


def test_correlation_ignores_direction(spark):
    x = np.random.default_rng(2).normal(size=(2, 30))
    df = spark.createDataFrame([(x[0].tolist(), x[1].tolist(), (-x[1]).tolist(), [1.0] * 30)], "a array<double>, b array<double>, c array<double>, d array<double>")
    r = df.select(scoring.abs_corr(F.col("a"), F.col("b")), scoring.abs_corr(F.col("a"), F.col("c")), scoring.abs_corr(F.col("a"), F.col("d"))).first()
    assert r[0] == pytest.approx(abs(np.corrcoef(x)[0, 1])) and r[1] == pytest.approx(r[0]) and r[2] == 0


def test_walk_of_two_nodes():
    r, _, _ = ppr.iterate(np.array([1.0, 3.0]), np.array([0]), np.array([1]), np.array([1.0]), 0.85, 1e-12)
    assert r == pytest.approx([0.25 / 1.2125, 0.79381], abs=1e-5)


def test_merges_add_weights_and_are_strict(spark):
    w = spark.createDataFrame([("A", "B", 5), ("A", "C", 3), ("B", "C", 3), ("C", "D", 4)], "c1 string, c2 string, w long")
    first = spark.createDataFrame([(x, x) for x in "ABCD"], "device string, cluster string")
    want = {"A": "A", "B": "A", "C": "A", "D": "D"}
    assert dict(clustering.merge_greedy(w, first, 4).collect()) == want == dict(clustering.merge_parallel(w, first, 4).collect())


def test_one_shadow_for_each_remote_callee(spark):
    services = spark.createDataFrame([("A", 1), ("B", 1), ("X", 2)], "service string, device int")
    calls = spark.createDataFrame([("A", "X", 1), ("B", "X", 1)], "src string, dst string, freq long")
    nodes, edges = subgraph.form(services, calls, clustering.initial(services))
    assert nodes.where("is_shadow").count() == 1 and edges.where("crosses").count() == 2


def test_measures(spark):
    r = spark.createDataFrame([(1,), (2,), (4,)], "rank int").agg(*evaluate.accuracy()).first()
    assert (r.acc_1, r.acc_2, r.acc_5, r.mar) == pytest.approx((1 / 3, 2 / 3, 1, 7 / 3)) and r.mrr == pytest.approx(0.583333, abs=1e-6)
    t = spark.createDataFrame([(10.0, 5.0), (20.0, 18.0)], "t_c double, t_d double").agg(*evaluate.reductions()).first()
    assert tuple(t) == pytest.approx((30, 23.3333), abs=1e-3)


def test_conflicting_clusters_share_their_views(spark):
    rows = [(0, 1, "m1", 0.5), (0, 1, "m2", 0.3), (0, 1, "cluster:2", 0.2), (0, 2, "m3", 0.6), (0, 2, "cluster:1", 0.4)]
    ranking = spark.createDataFrame(rows, "scenario int, grp long, node string, r double")
    linked = spark.createDataFrame([(0, 1, 2), (0, 2, 1)], "scenario int, grp long, other long")
    got = {r.node: r.score for r in aggregate.combine(ranking, linked).collect()}
    assert got == pytest.approx({"m1": 0.35, "m2": 0.21, "m3": 0.36})


def test_callers_share_a_device(spark):
    services = spark.range(6).select(F.col("id").alias("service"))
    freq = spark.createDataFrame([(0, 1, 9), (1, 2, 8), (3, 4, 7), (4, 5, 6), (2, 3, 1)], "src long, dst long, freq long")
    at = dict(topology.place_by_communication(services, freq, 2).collect())
    assert at[0] == at[1] == at[2] != at[3] == at[4] == at[5]


def test_pairs_beyond_the_largest_size_stay_apart(spark):
    w = spark.createDataFrame([(0, 1, 5), (1, 2, 4), (2, 3, 3)], "c1 long, c2 long, w long")
    one = spark.range(4).select(F.col("id").alias("device"), F.col("id").alias("cluster"))
    assert dict(clustering.merge_greedy(w, one, 0, 2).collect()) == {0: 0, 1: 0, 2: 2, 3: 2}
    assert dict(clustering.merge_greedy(w, one, 0).collect()) == {0: 0, 1: 0, 2: 0, 3: 0}


def test_features_and_learned_stand_in(spark):
    nodes = spark.createDataFrame([(k, n, float(x)) for k in range(20) for n, x in (("a", 1 + k % 3), ("b", 9), ("c", 0))], "scenario int, node string, s double")
    edges = spark.createDataFrame([(k, "a", "b", 2.0) for k in range(20)], "scenario int, src string, dst string, w double")
    sc = localize.Scores(nodes, edges, None, None)
    x = {r.node: r.x for r in baselines.node_features(sc).where("scenario = 1").collect()}
    assert x["b"] == [9.0, 2.0, 2.0, 0.0, 0.0, 0.0, 0.0] and x["a"] == [2.0, 0.0, 0.0, 0.0, 2.0, 9.0, 0.0] and x["c"] == [0.0] * 7
    truth = spark.createDataFrame([(k, "b") for k in range(20)], "scenario int, root string")
    top = baselines.learned_stand_in(sc, truth).where("rank = 1").select("scenario", "node").collect()
    assert {(r.scenario, r.node) for r in top} == {(k, "b") for k in range(0, 20, 2)}
