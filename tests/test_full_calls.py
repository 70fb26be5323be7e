import __spark_entry__
from edgeloc.sources import scenarios


def test_noise_is_of_all_events_and_weights_of_all_calls(spark):
    d = "/root/testdata/sf0.01"
    got = scenarios.noise_windows(spark, d).collect()
    assert len(got) == spark.read.parquet(f"{d}/events.parquet").count() > 1000 and all(len(r.u) == scenarios.BINS for r in got)
    by = {r["at"]: r.u for r in got}
    assert all(by[k][1] == by[(k + 1) % len(by)][0] for k in by)
    q = __spark_entry__.queries()
    calls = q["wl_freq_nation"](spark, d).groupBy().sum("freq").first()[0]
    assert q["clu_weights_full"](spark, d).groupBy().sum("w").first()[0] == calls > q["clu_weights"](spark, d).groupBy().sum("w").first()[0]
