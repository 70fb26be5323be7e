import json

import pytest

from edgeloc.operators import exchange, localize
from edgeloc.plans import surface
from edgeloc.sources import scenarios
from edgeloc.streaming import detect


def test_views_functions_and_trace(spark):
    surface.register(spark)
    row = spark.sql("SELECT feature_radius(2.0D, 4.0D, 10.0D) AS r, node_kind('shadow:x') AS a, node_kind('cluster:1') AS b, node_kind('7') AS c, time_reduction(20.0D, 15.0D) AS t").first()
    assert (row.r, row.a, row.b, row.c, row.t) == (1.0, "shadow", "cluster", "service", 25.0)
    steps = spark.sql("SELECT * FROM walk_steps(array('a', 'b'), array(1.0D, 3.0D), array('a'), array('b'), array(1.0D), 0.85D, 200)").collect()
    last = {r.node: r.r for r in steps if r.step == 200}
    assert len(steps) == 400 and last == pytest.approx({"a": 0.25 / 1.2125, "b": 0.793814}, abs=1e-5)


def test_steps_of_a_run_can_be_asked_in_sql(spark):
    i = scenarios.build(spark, "/root/testdata/sf0.01", n_scenarios=6)
    sc = localize.score(i)
    r = localize.decentralized(i, sc)
    views = surface.views(i, sc, r)
    assert set(views) == {"services", "calls", "clusters", "subgraph_nodes", "subgraph_edges", "series", "flags", "scores", "rankings"}
    assert spark.sql("SELECT count(*) AS n FROM flags f LEFT ANTI JOIN series s ON s.scenario = f.scenario AND s.entity = f.entity AND s.metric = f.metric").first().n == 0
    assert spark.sql("SELECT count(*) AS n FROM (SELECT scenario, grp, sum(r) AS t FROM rankings GROUP BY 1, 2) WHERE abs(t - 1) > 1e-6").first().n == 0
    m = surface.message_json(exchange.messages(r.cross, r.means)).collect()
    assert m and {json.loads(x.body)["kind"] for x in m} == {"wait", "score"}
    maps = surface.ranking_maps(r.ranking).first().r
    assert sum(maps.values()) == pytest.approx(1)
    v = surface.volume(views["series"]).first()
    assert v.rows == 6 * 450 and v.metrics == 9 and abs(v.entities - 125) <= 6


def test_streams_join_tables_and_streams(spark, tmp_path):
    kinds = {"metric": "service string, ts timestamp, value double", "latency": "service string, at timestamp, latency double"}
    rows = {"metric": [("a", "2024-01-01 10:00:00", 1.0), ("b", "2024-01-01 10:00:00", 2.0)], "latency": [("a", "2024-01-01 09:30:00", 5.0), ("a", "2024-01-01 08:00:00", 6.0), ("b", "2024-01-01 10:30:00", 7.0)]}
    streams = {}
    for name, kind in kinds.items():
        when = "ts" if name == "metric" else "at"
        df = spark.createDataFrame(rows[name], kind.replace("timestamp", "string"))
        df.withColumn(when, df[when].cast("timestamp")).write.parquet(f"{tmp_path}/{name}")
        streams[name] = spark.readStream.schema(kind).parquet(f"{tmp_path}/{name}")
    services = spark.createDataFrame([("a", 1)], "service string, device int")
    assert [(r.service, r.device) for r in detect.run_once(detect.with_services(streams["metric"], services), "with_table", "append").collect()] == [("a", 1)]
    assert [(r.service, r.latency) for r in detect.run_once(detect.with_latency(streams["metric"], streams["latency"]), "with_stream", "append").collect()] == [("a", 5.0)]
