"""Hand cases and checks of topology, metrics, vectors, co-clusters, tuning and streams."""

import tracemalloc
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgeloc.operators import birch, metrics, scoring, topology, tune
from edgeloc.sources import scenarios, tables
from edgeloc.streaming import detect


def test_a_hot_trace_in_chunks_gives_the_same_calls(spark):
    rng = np.random.default_rng(2)
    spans = spark.createDataFrame([(1, k, int(rng.integers(0, 4)), k // 7) for k in range(100)] + [(2, k, int(rng.integers(0, 4)), k // 7) for k in range(0, 60, 9)] + [(3, 0, 1, 0)], "trace int, pos int, service int, chunk int")
    one, many = (sorted(map(tuple, topology.calls_from_traces(spans, carry=("pos",), chunk=c).collect())) for c in (None, "chunk"))
    assert one == many and len(one) > 50


def test_graph_keeps_known_ends(spark):
    services = spark.createDataFrame([("a", 1), ("b", 1)], "service string, device int")
    freq = spark.createDataFrame([("a", "b", 3), ("a", "x", 1)], "src string, dst string, freq long")
    nodes, calls = topology.graph(services, freq)
    assert {tuple(r) for r in nodes.collect()} == {("a", "service"), ("b", "service"), ("1", "device")} and [tuple(r) for r in calls.collect()] == [("a", "b", 3)]
    assert [r.service for r in topology.dangling(services.select("service"), freq).collect()] == ["x"]


def test_placements(spark):
    services = spark.range(7).select(F.col("id").alias("service"))
    devices = spark.createDataFrame([(0, 1.0), (1, 5.0), (2, 3.0)], "device int, capacity double")
    at = dict(topology.place_by_capacity(services, devices).collect())
    assert at == {0: 1, 1: 2, 2: 0, 3: 1, 4: 2, 5: 0, 6: 1}
    assert dict(topology.place_scattered(services, 3, F.col("service")).collect()) == {k: k % 3 for k in range(7)}


def test_alignment_and_scaling(spark):
    series = spark.createDataFrame([("e", "m", 1, 2.0), ("e", "m", 3, 4.0)], "entity string, metric string, t int, value double")
    values = lambda how: [r.value for r in metrics.align(series, 0, 4, how).orderBy("t").collect()]
    assert values("zero") == [0, 2, 0, 4, 0] and values("last") == [0, 2, 2, 4, 4]
    df = spark.createDataFrame([([1.0, 3.0, 5.0],), ([2.0, 2.0, 2.0],)], "v array<double>")
    scaled = lambda how: [r[0] for r in df.select(metrics.normalized(F.col("v"), how)).collect()]
    assert scaled("minmax") == [[0, 0.5, 1], [0, 0, 0]]
    assert scaled("zscore")[0] == pytest.approx([-1.224745, 0, 1.224745], abs=1e-6) and scaled("zscore")[1] == [0, 0, 0]
    assert scaled("l2")[1] == pytest.approx([3**-0.5] * 3)


def test_devices_attach_to_their_services(spark):
    spans = spark.createDataFrame([(1, "a", 1, 5.0, 0), (1, "b", 1, 7.0, 0)], "trace int, service string, device int, latency double, t int")
    got = metrics.device_series(spans, F.col("t"), attach=spans.select("service", "device")).where("metric = 'device_max'").collect()
    assert {(r.entity, r.value) for r in got} == {("a", 7.0), ("b", 7.0)}


def test_vector_features_do_not_depend_on_partitions(spark):
    x = np.random.default_rng(4).normal(size=(300, 5))
    df = spark.createDataFrame([(k, r.tolist(), k % 3) for k, r in enumerate(x)], "id int, v array<double>, label int")
    rows = [[(r.n, round(r.radius, 9)) for r in birch.fit_vectors(df.repartition(n), "v", 1.2, key="id", parts=9, fan=3).orderBy("cf").collect()] for n in (1, 7)]
    assert rows[0] == rows[1] and sum(n for n, _ in rows[0]) == 300 and len(rows[0]) < 300
    assert spark.createDataFrame([], df.schema).count() == 0
    tight = spark.createDataFrame([(k, [float(k % 4) * 10, 0.0], k % 4) for k in range(40)], df.schema)
    fit = birch.fit_vectors(tight, "v", 0.5, key="id", parts=3)
    got = birch.purity(tight, "v", "label", fit).first()
    assert (got.features, got.purity) == (4, 1.0)


def test_purity_holds_a_tile_of_distances_whatever_the_features(spark):
    rng = np.random.default_rng(7)
    x, centres = rng.normal(size=(3000, 8)), rng.normal(size=(6000, 8))
    want = np.concatenate([((p[:, None] - centres[None]) ** 2).sum(-1).argmin(1) for p in np.split(x, 30)])
    best, cf = np.full(len(x), np.inf), np.zeros(len(x), dtype=np.int32)
    tracemalloc.start()
    birch.nearest(x, centres, 0, best, cf)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert (cf == want).all() and peak < 16 << 20  # the whole matrix takes 144 MB
    df = spark.createDataFrame([(k, r.tolist(), k % 3 if k % 7 else None) for k, r in enumerate(x[:400])], "id int, v array<double>, label int")
    feats = spark.createDataFrame([(k, c.tolist()) for k, c in enumerate(centres[:100])], "cf int, centroid array<double>")
    at = ((x[:400, None] - centres[None, :100]) ** 2).sum(-1).argmin(1)
    groups = Counter((int(c), k % 3 if k % 7 else None) for k, c in enumerate(at))
    most = sum(max(n for (c, _), n in groups.items() if c == f) for f in set(at.tolist()))
    for chunk in (1 << 20, 40 * 64):  # one chunk, and three
        got = birch.purity(df, "v", "label", feats, chunk_bytes=chunk).first()
        assert (got.features, round(got.purity, 9)) == (len(set(at.tolist())), round(most / 400, 9))


def test_cocluster_keeps_the_largest_like_group(spark):
    t = np.arange(20.0)
    series = {"up": t, "down": -t, "steps": t + 0.1 * (t % 2), "wave": np.sin(t), "flat": 5 + 0 * t}
    df = spark.createDataFrame([(0, "n", m, v.tolist(), True) for m, v in series.items()], "scenario int, node string, metric string, v array<double>, is_anomalous boolean")
    assert {r.metric for r in birch.cocluster(df, ["scenario", "node"]).collect()} == {"up", "down", "steps"}


def test_explanations_name_callers(spark):
    t = np.arange(12.0)
    flags = spark.createDataFrame([(0, "n", m, v.tolist(), True) for m, v in (("a", t), ("b", t * 2), ("c", np.cos(t)))], "scenario int, node string, metric string, v array<double>, is_anomalous boolean")
    calls = spark.createDataFrame([(0, "m", "n", "p90", (-t).tolist(), True)], "scenario int, src string, dst string, metric string, v array<double>, is_anomalous boolean")
    got = [(r.a, r.b, round(r["corr"], 6)) for r in scoring.explain(flags, 2, calls=scoring.call_influence(calls, flags)).collect()]
    assert set(got) == {("a", "b", 1.0), ("call", "m", 1.0)}
    parts = {r.src: r.s for r in scoring.score_parts(flags, calls).collect()}
    assert parts["m"] == pytest.approx(1.0) and parts[None] == pytest.approx(1 + 2 * abs(np.corrcoef(t, np.cos(t))[0, 1]))


def test_parzen_search_beats_its_random_start():
    far = lambda p: -((np.log(p["x"]) - np.log(0.01)) ** 2) - (p["y"] - 0.3) ** 2
    sizes = []

    def judge(batch):
        sizes.append(len(batch))
        return [far(p) for p in batch]

    done = tune.tpe(judge, {"x": (1e-4, 1, "log"), "y": (0, 1, "lin")}, trials=60, batch=8, seed=3)
    assert len(done) == 60 and sizes == [8] * 7 + [4] and all(1e-4 <= p["x"] <= 1 and 0 <= p["y"] <= 1 for p, _ in done)
    assert max(y for _, y in done[8:]) > max(y for _, y in done[:8]) and np.median([y for _, y in done[-20:]]) > np.median([y for _, y in done[:8]])
    assert tune.grid(judge, {"x": [0.01, 0.1], "y": [0.3]})[0] == ({"x": 0.01, "y": 0.3}, 0.0)


def test_noise_goes_round(spark):
    got = {r["at"]: r.u for r in scenarios.noise_windows(spark, "/root/testdata/sf0.001").collect()}
    assert all(got[k][1] == got[(k + 1) % len(got)][0] for k in got)


def test_formats_and_partitions(spark, tmp_path):
    df = spark.createDataFrame([(1, "a", 2.0), (2, "b", 3.0)], "k int, p string, x double")
    for fmt in ("parquet", "orc", "json", "csv"):
        df.write.format(fmt).save(f"{tmp_path}/{fmt}")
        assert sorted(map(tuple, tables.read(spark, fmt, f"{tmp_path}/{fmt}", df.schema).collect())) == [(1, "a", 2.0), (2, "b", 3.0)]
    place = f"{tmp_path}/parts"
    tables.write_partitioned(df, place, "p")
    tables.write_partitioned(df.where("p = 'a'").withColumn("x", F.lit(9.0)), place, "p")
    assert {(r.p, r.x) for r in spark.read.parquet(place).collect()} == {("a", 9.0), ("b", 3.0)}


def events(spark, folder, rows, name):
    df = spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string")
    df.withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.parquet(f"{folder}/tmp_{name}")
    import glob
    import os

    os.rename(glob.glob(f"{folder}/tmp_{name}/*.parquet")[0], f"{folder}/events_{name}.parquet")


def test_stream_equals_batch_drops_late_rows_and_restarts(spark, tmp_path):
    rng = np.random.default_rng(5)
    folder = f"{tmp_path}/in"
    (tmp_path / "in").mkdir()
    rows = [(k, f"2024-01-{1 + k // 20:02d} 0{k % 10}:00:00", 1, "ab"[k % 2], float(rng.random()), "{}") for k in range(100)]
    samples = lambda: detect.event_stream(spark, folder).select(F.col("event_type").alias("entity"), "value", "ts", "event_id")
    mark = f"{tmp_path}/state"
    events(spark, folder, rows[:60], "a")
    detect.to_incidents(detect.flags(samples(), 0.05), f"{tmp_path}/out", mark).awaitTermination()
    events(spark, folder, rows[60:], "b")
    detect.to_incidents(detect.flags(samples(), 0.05), f"{tmp_path}/out", mark).awaitTermination()  # a new query goes on from the kept state
    got = {r.entity: r.n for r in spark.read.parquet(f"{tmp_path}/out").groupBy("entity").agg(F.max_by("n_features", "batch").alias("n")).collect()}
    ordered = lambda e, part: [r[4] for r in sorted((r for r in part if r[3] == e), key=lambda r: (r[1], r[0]))]
    batch = spark.createDataFrame([(e, ordered(e, rows[:60]) + ordered(e, rows[60:])) for e in "ab"], "entity string, v array<double>")
    assert got == {r.entity: r.n_features for r in birch.detect(batch, 0.05).collect()}
    # a row that comes more than a day behind the watermark is not counted
    events(spark, folder, [(900, "2024-01-20 00:00:00", 1, "a", 1.0, "{}")], "c")
    events(spark, folder, [(901, "2024-01-02 00:00:00", 1, "a", 1.0, "{}"), (902, "2024-01-20 01:00:00", 1, "a", 1.0, "{}")], "d")
    daily = detect.run_once(detect.daily_series(detect.event_stream(spark, folder)), "late_rows", "update")
    got = {(r.day, r.event_type): r.n for r in daily.groupBy("day", "event_type").agg(F.max("n").alias("n")).collect()}
    want = {(d, e): 10 for d in range(5) for e in "ab"} | {(19, "a"): 2}
    assert got == want
