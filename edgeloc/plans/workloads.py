"""The experiment workloads and operator queries, each a function of (spark, sf_dir)."""

from __future__ import annotations



from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgeloc.operators import aggregate, baselines, birch, clustering, evaluate, exchange, localize, metrics, ppr, scoring, subgraph, topology, tune
from edgeloc.sources import scenarios
from edgeloc.sources.storage import checkpointed
from edgeloc.sources.tables import event_spans, load, supplier_spans

Q: dict = {}


def query(f):
    Q[f.__name__] = f
    return f


def r6(c):
    return F.round(c, 6)


def _day(t="day"):
    return F.datediff(F.col(t), F.lit("2024-01-01").cast("date"))


def _event_calls(s, d):
    return topology.calls_from_traces(event_spans(s, d), carry=("latency", "day"), chunk="day")


def _nation_calls(s, d, timed=True):
    """Calls between nations, with latency and order day if timed."""
    place = load(s, d, "supplier").select(F.col("s_suppkey").alias("src"), F.col("s_nationkey").cast("long").alias("a"))
    more = ("latency", "day") if timed else ()
    calls = topology.calls_from_traces(supplier_spans(s, d, timed), carry=("device", *more))
    return calls.join(place, "src").where("a <> device").select("trace", F.col("a").alias("src"), F.col("device").alias("dst"), *more)


# ---- topology


@query
def wl_calls_supplier(s, d):
    return topology.calls_from_traces(supplier_spans(s, d, timed=False))


@query
def wl_freq_supplier(s, d):
    return topology.call_frequency(wl_calls_supplier(s, d))


@query
def wl_freq_nation(s, d):
    return topology.call_frequency(_nation_calls(s, d, timed=False))


@query
def wl_calls_events(s, d):
    return topology.calls_from_traces(event_spans(s, d), carry=("latency",), chunk="day")


@query
def wl_freq_events(s, d):
    return topology.call_frequency(wl_calls_events(s, d))


@query
def op_unlinked_services(s, d):
    services = load(s, d, "supplier").select(F.col("s_suppkey").alias("service"))
    return topology.unlinked(services, wl_freq_supplier(s, d).where("freq > 1"))


@query
def op_host_device(s, d):
    sup = load(s, d, "supplier").groupBy(F.col("s_nationkey").cast("long").alias("device")).agg(F.sum("s_acctbal").alias("capacity"))
    return topology.pick_host(sup, sup.select("device", (F.col("device") % 3).alias("cluster")))


@query
def conv_calls(s, d):
    spans = load(s, d, "conversations").select(F.col("conv_id").alias("trace"), F.col("turn").alias("pos"), F.col("role").alias("service"))
    return topology.call_frequency(topology.calls_from_traces(spans))


@query
def web_links(s, d):
    """Links between pages' hosts; a relative one stays on its host."""
    p = load(s, d, "pages").select(F.regexp_extract("url", "://([^/?#]*)", 1).alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'))).alias("href"))
    host = F.regexp_extract("href", "://([^/?#]*)", 1)
    return p.select("src", F.when(host == "", F.col("src")).otherwise(host).alias("dst")).groupBy("src", "dst").agg(F.count("*").alias("freq"))


@query
def op_session_traces(s, d):
    """Sessions of users, cut where three days pass without an event."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = (F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp"))) > 3 * 86_400_000_000
    e = load(s, d, "events").select("user_id", "ts", "event_id", F.coalesce(gap, F.lit(False)).cast("int").alias("cut"))
    e = e.withColumn("session", F.sum("cut").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return e.groupBy("user_id", "session").agg(F.count("*").alias("n"))


@query
def op_span_lead(s, d):
    """Time from each event of a user to the next, in microseconds; null at the last."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(s, d, "events").select("event_id", (F.lead(us).over(w) - us).alias("gap_us"))


@query
def op_href_links(s, d):
    href = F.regexp_extract_all("html", F.lit('href="([^"]*)"'))
    return load(s, d, "pages").select("page_id", F.explode(href).alias("href")).groupBy("page_id").agg(F.count("*").alias("n_links"), F.countDistinct("href").alias("n_targets"))


# ---- metrics


@query
def wl_series_events(s, d):
    return metrics.node_series(event_spans(s, d), _day()).withColumn("value", r6("value"))


@query
def wl_series_supplier(s, d):
    item = load(s, d, "lineitem").join(load(s, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    t = F.year("l_shipdate") * 4 + F.quarter("l_shipdate")
    return item.groupBy(F.col("s_nationkey").cast("long").alias("entity"), t.alias("t")).agg(F.count("*").alias("n"), r6(F.sum("l_quantity")).alias("qty"), F.sum(F.round(F.col("l_discount") * 100).cast("long")).alias("disc"), F.sum(F.round(F.col("l_tax") * 100).cast("long")).alias("tax"))


@query
def wl_edge_latency(s, d):
    half = F.year("day") * 2 + F.floor((F.month("day") - 1) / 6)
    return metrics.edge_series(_nation_calls(s, d), half).withColumn("value", r6("value"))


@query
def wl_edge_latency_sketch(s, d):
    """The percentiles of wl_edge_latency over all time, from mergeable sketches whose rank error is at most one in 10,000: how far each is from the exact rank, in shares of the calls."""
    calls = _nation_calls(s, d).withColumn("latency", F.col("latency").cast("double"))
    names = ["p50", "p90", "p99"]
    got = metrics.edge_series(calls, F.lit(0), accuracy=10_000).where("metric in ('p50', 'p90', 'p99')").groupBy("src", "dst").pivot("metric", names).agg(F.first("value"))
    met = calls.join(got, ["src", "dst"]).groupBy("src", "dst")
    off = [F.greatest(F.avg((F.col("latency") < F.col(n)).cast("double")) - q, q - F.avg((F.col("latency") <= F.col(n)).cast("double")), F.lit(0.0)) for n, q in zip(names, (0.5, 0.9, 0.99))]
    # a rank is told to one part in n of the calls at best
    return met.agg(F.count("*").alias("n"), *(o.alias(f"off_{n}") for n, o in zip(names, off))).select("src", "dst", *((F.col(f"off_{n}") <= 1e-4 + 1 / F.col("n")).alias(f"{n}_ok") for n in names))


@query
def op_edge_percentiles(s, d):
    return metrics.edge_series(_event_calls(s, d), F.floor(_day() / 10)).withColumn("value", r6("value"))


@query
def op_series_align(s, d):
    counts = event_spans(s, d).groupBy(F.col("service").alias("entity"), F.lit("count").alias("metric"), _day().alias("t")).agg(F.count("*").cast("double").alias("value"))
    return metrics.align(counts, 0, 29)




def _packed(s, d):
    return metrics.pack(op_series_align(s, d))


@query
def op_l2_normalize(s, d):
    z = _packed(s, d).withColumn("v", metrics.normalized(F.col("v")))
    return z.select("entity", F.posexplode("v").alias("t", "x")).select("entity", "t", r6("x").alias("value"))


@query
def op_sliding_rate(s, d):
    e = load(s, d, "events")
    return e.groupBy(F.window("ts", "2 days", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.datediff(F.col("w.start").cast("date"), F.lit("2024-01-01").cast("date")).alias("start"), "event_type", "n")


@query
def op_asof_metric(s, d):
    """For each click the last purchase value of the user at or before it: a union and a window, no range join."""
    e = load(s, d, "events").select("event_id", "user_id", "ts", "event_type", "value")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("value")), ignorenulls=True).over(w)
    return e.select("event_id", "event_type", last.alias("last_value")).where("event_type = 'click'").select("event_id", "last_value")


@query
def op_interval_join(s, d):
    """Events at most an hour before a large one of the same user: hour buckets make the interval an equi join."""
    e = load(s, d, "events").select("event_id", "user_id", "ts", "value", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    big = e.where("value > 200").select(F.col("event_id").alias("incident"), F.col("user_id").alias("u"), F.col("us").alias("t0"), F.explode(F.array(F.floor(F.col("us") / hour), F.floor(F.col("us") / hour) - 1)).alias("b"))
    j = e.join(big, (F.col("user_id") == F.col("u")) & (F.floor(e["us"] / hour) == big["b"]))
    return j.where((F.col("us") <= F.col("t0")) & (F.col("us") >= F.col("t0") - hour)).groupBy("incident").agg(F.count("*").alias("n"))


@query
def op_props_json(s, d):
    return load(s, d, "events").groupBy(F.floor(F.get_json_object("props", "$.k").cast("int") / 20).alias("device")).agg(F.count("*").alias("n"))


@query
def op_device_series(s, d):
    return metrics.device_series(event_spans(s, d), _day()).withColumn("value", r6("value"))


@query
def op_link_series(s, d):
    place = event_spans(s, d).select("service", "device").distinct()
    return metrics.link_series(_event_calls(s, d), place, F.floor(_day() / 10)).withColumn("value", r6("value"))


# ---- detection and scores


@query
def det_gap_events(s, d):
    z = _packed(s, d).withColumn("z", metrics.normalized(F.col("v")))
    return z.select("entity", birch.detect_gap(F.col("z"), 0.03).alias("n_groups"))


@query
def det_birch_events(s, d):
    z = _packed(s, d).withColumn("z", metrics.normalized(F.col("v")))
    return birch.detect(z, birch.BETA, "z").select("entity", "metric", "n_features", "is_anomalous")


@query
def det_birch_sweep(s, d):
    z = _packed(s, d).withColumn("v", metrics.normalized(F.col("v")))
    return birch.sweep(z, [0.01, 0.02, 0.03, 0.05, 0.07, 0.1]).groupBy("beta").agg(F.sum(F.col("is_anomalous").cast("int")).alias("flagged"))


@query
def det_birch_vectors(s, d):
    return birch.fit_vectors(load(s, d, "embeddings"), "embedding", 0.9, key="vec_id").select("cf", "n", r6("radius").alias("radius"))


@query
def det_purity(s, d):
    """How well the features of vectors tell the label, beside the share of the commonest label."""
    e = load(s, d, "embeddings")
    got = birch.purity(e, "embedding", "label", birch.fit_vectors(e, "embedding", 0.9, key="vec_id"))
    most = e.groupBy("label").agg(F.count("*").alias("n")).agg((F.max("n") / F.sum("n")).alias("commonest"))
    return got.crossJoin(most).select("features", r6("purity").alias("purity"), r6("commonest").alias("commonest"))  # one row each


@query
def det_edges(s, d):
    """Flags of the nations' edge latency series: half-years, missing ones carried forward, unit length."""
    half = (F.year("day") * 2 + F.floor((F.month("day") - 1) / 6)).cast("int")
    e = metrics.edge_series(_nation_calls(s, d), half)
    ends = e.agg(F.min("t"), F.max("t")).first()
    series = e.select(F.concat_ws(">", F.col("src").cast("string"), F.col("dst").cast("string")).alias("entity"), "metric", "t", "value")
    z = metrics.pack(metrics.align(series, ends[0] or 0, ends[1] or 0, "last")).withColumn("z", metrics.normalized(F.col("v")))
    return birch.detect(z, 0.05, "z").groupBy("metric").agg(F.count("*").alias("series"), F.sum(F.col("is_anomalous").cast("int")).alias("flagged"))


@query
def op_abs_corr_pairs(s, d):
    """Pairs of event services by the correlation of their daily counts, made in rows of a device."""
    z = _packed(s, d).withColumn("device", F.substring_index("entity", "_", -1)).groupBy("device").agg(F.array_sort(F.collect_list(F.struct("entity", "v"))).alias("a"))
    pairs = F.flatten(F.transform("a", lambda x, i: F.transform(F.slice("a", i + 2, F.size("a")), lambda y: F.struct(x["entity"].alias("e1"), y["entity"].alias("e2"), scoring.abs_corr(x["v"], y["v"]).alias("corr")))))
    return z.select(F.explode(pairs).alias("p")).select("p.e1", "p.e2", r6("p.corr").alias("corr"))


def _active(s, d, bins):
    """Metrics of event services, packed, each flagged where its range is above two thirds of its largest value."""
    series = metrics.align(metrics.node_series(event_spans(s, d), F.floor(_day() / bins).cast("int")), 0, 30 // bins - 1)
    v = F.col("v")
    return metrics.pack(series).select(F.lit(0).alias("scenario"), F.col("entity").alias("node"), "metric", "v", ((F.array_max(v) - F.array_min(v)) * 3 > F.array_max(v) * 2).alias("is_anomalous"))


@query
def score_metric(s, d):
    return scoring.metric_score(_active(s, d, 1)).select("node", r6("s_metric").alias("s_metric"))


@query
def score_edge_influence(s, d):
    e = metrics.edge_series(_event_calls(s, d), F.floor(_day() / 3).cast("int")).withColumn("entity", F.concat_ws(">", "src", "dst"))
    e = metrics.pack(metrics.align(e.select("entity", "metric", "t", "value"), 0, 9))
    end = F.split("entity", ">")
    e = e.select(F.lit(0).alias("scenario"), end[0].alias("src"), end[1].alias("dst"), "metric", "v", (F.array_min("v") == 0).alias("is_anomalous"))
    return scoring.edge_influence(e, _active(s, d, 3)).select("node", r6("s_edge").alias("s_edge"))


@query
def op_spearman(s, d):
    z = _packed(s, d)
    a, b = z.where("entity like '%\\_0'"), z.where("entity like '%\\_1'")
    kind = lambda c: F.substring_index(c, "_", 1)
    j = a.select(kind("entity").alias("kind"), F.col("v").alias("x")).join(b.select(kind("entity").alias("kind"), F.col("v").alias("y")), "kind")
    return j.select("kind", r6(scoring.abs_corr(F.col("x"), F.col("y"), "spearman")).alias("corr"))


@query
def op_spearman_pairs(s, d):
    """Rank correlations of all device pairs of an event type, made in rows of the type."""
    z = _packed(s, d).withColumn("kind", F.substring_index("entity", "_", 1)).groupBy("kind").agg(F.array_sort(F.collect_list(F.struct("entity", "v"))).alias("a"))
    pairs = F.flatten(F.transform("a", lambda x, i: F.transform(F.slice("a", i + 2, F.size("a")), lambda y: F.struct(x["entity"].alias("e1"), y["entity"].alias("e2"), scoring.abs_corr(x["v"], y["v"], "spearman").alias("corr")))))
    return z.select(F.explode(pairs).alias("p")).select("p.e1", "p.e2", r6("p.corr").alias("corr"))


@query
def op_personalization(s, d):
    f = wl_freq_nation(s, d).groupBy(F.col("dst").alias("node")).agg(F.sum("freq").alias("s")).withColumn("grp", F.col("node") % 3)
    return scoring.share(f, "s", "p", "grp").select("grp", "node", r6("p").alias("p"))


@query
def op_transition(s, d):
    return scoring.share(wl_freq_nation(s, d), "freq", "p", "src").select("src", "dst", r6("p").alias("p"))


@query
def op_ppr_k10(s, d):
    edges = wl_freq_nation(s, d).select("src", "dst", F.col("freq").cast("double").alias("w"))
    nodes = edges.groupBy(F.col("dst").alias("node")).agg(F.sum("w").alias("s"))
    return ppr.solve_steps(nodes, edges, 0.5, 10).select("node", F.round("r", 8).alias("r"))


@query
def op_topk_causes(s, d):
    return ppr.rank(op_ppr_k10(s, d)).where("rank <= 5").select("node", "r", "rank")


@query
def web_ppr(s, d):
    edges = web_links(s, d).select("src", "dst", F.col("freq").cast("double").alias("w"))
    ends = edges.select(F.col("src").alias("node"), "w").union(edges.select("dst", "w"))
    r = ppr.solve_steps(ends.groupBy("node").agg(F.sum("w").alias("s")), edges, steps=12)
    return r.select("node", F.round("r", 6).alias("r"))


# ---- clusters and subgraphs


def _clustered(s, d, full=False):
    freq = wl_freq_nation(s, d) if full else scenarios.thinned_nation_calls(s, d)
    services = load(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("service"), F.col("n_nationkey").cast("long").alias("device"))
    first = clustering.initial(services)
    freq = checkpointed(freq)  # a row for each pair of nations, read several times
    w = checkpointed(clustering.weights(freq, services, first))
    return freq, services, first, w


@query
def clu_initial(s, d):
    return _clustered(s, d)[2]


@query
def clu_weights(s, d):
    return _clustered(s, d)[3]


@query
def clu_weights_full(s, d):
    """Weights over all calls between nations, none thinned."""
    return _clustered(s, d, True)[3]


def _map(s, d, full=False):
    freq, services, first, w = _clustered(s, d, full)
    return freq, services, clustering.merge_parallel(w, first, clustering.threshold(w, 0.01))


@query
def clu_map(s, d):
    return _map(s, d)[2]


@query
def clu_map_full(s, d):
    return _map(s, d, True)[2]


@query
def clu_map_greedy(s, d):
    _, _, first, w = _clustered(s, d)
    return clustering.merge_greedy(w, first, clustering.threshold(w, 0.01))


@query
def clu_per_scenario(s, d):
    """How many clusters each scenario has, from the call graph of its own window of traces; all windows are merged in one job."""
    return scenarios.scenario_clusters(s, d).groupBy("scenario").agg(F.countDistinct("cluster").alias("clusters"))


@query
def clu_count(s, d):
    return evaluate.clusters_per_scenario(scenarios.scenario_clusters(s, d))


TAUS = (0.001, 0.005, 0.0075, 0.01, 0.02, 0.03, 0.05, 0.1)


@query
def clu_tau_sweep(s, d):
    """(sweep, tau, clusters): clusters of the thinned calls at several thresholds, all merged in one job by key."""
    _, _, first, w = _clustered(s, d)
    taus = F.explode(F.array(*(F.struct(F.lit(k).alias("sweep"), F.lit(t).alias("share")) for k, t in enumerate(TAUS))))
    total = w.groupBy().agg(F.sum("w").alias("all"))
    many = w.crossJoin(F.broadcast(total)).select("*", taus.alias("x")).select("x.sweep", "c1", "c2", "w", (F.col("x.share") * F.col("all")).alias("tau"))  # one row
    start = first.select(taus.alias("x"), "device", "cluster").select("x.sweep", "device", "cluster")
    got = clustering.merge_parallel(checkpointed(many), start, None, keys=("sweep",)).groupBy("sweep").agg(F.countDistinct("cluster").alias("clusters"))
    return got.select("sweep", F.element_at(F.array(*map(F.lit, TAUS)), F.col("sweep") + 1).alias("tau"), "clusters")


@query
def clu_quality(s, d):
    """Sizes and cut ratios of the clusters (E12)."""
    return clustering.quality(*_map(s, d)).withColumn("ratio", r6("ratio"))


@query
def clu_cut_ratio(s, d):
    return clustering.cut_ratio(*_map(s, d)).withColumn("ratio", r6("ratio"))


@query
def place_cut_ratio(s, d):
    """Cut ratios of the recorded and of other placements, each clustered at one per cent."""
    freq, services, first, w = _clustered(s, d)
    cap = load(s, d, "supplier").groupBy(F.col("s_nationkey").cast("long").alias("device")).agg(F.sum("s_acctbal").alias("capacity"))
    out = None
    for name, place in (("recorded", services), ("scattered", topology.place_scattered(services, 8, F.col("service"))), ("capacity", topology.place_by_capacity(services, cap.orderBy(F.desc("capacity"), "device").limit(8))), ("communication", topology.place_by_communication(services, freq, 8))):
        one = clustering.initial(place)
        wt = clustering.weights(freq, place, one)
        c = clustering.cut_ratio(freq, place, clustering.merge_greedy(wt, one, clustering.threshold(wt, 0.01)))
        c = c.agg(F.lit(name).alias("placement"), F.count("*").alias("clusters"), r6(F.sum("intra") / (F.sum("intra") + F.sum("inter"))).alias("inside"))
        out = c if out is None else out.union(c)
    return out


@query
def sub_nodes(s, d):
    freq, services, cmap = _map(s, d)
    return subgraph.form(services, freq, cmap)[0]


@query
def sub_edges(s, d):
    freq, services, cmap = _map(s, d)
    return subgraph.form(services, freq, cmap)[1].select("cluster", "src", "dst", "freq", "crosses")


@query
def sub_shadow(s, d):
    return sub_nodes(s, d).where("is_shadow").groupBy("cluster").agg(F.count("*").alias("shadows"))


@query
def op_two_way_crossings(s, d):
    freq, services, cmap = _map(s, d)
    return subgraph.two_way(subgraph.form(services, freq, cmap)[1])


def _calls_as_scores(s, d):
    """Thinned calls as scores: nodes(scenario, grp, node, s) by calls received, edges by frequency, and of(node, cluster)."""
    freq, services, cmap = _map(s, d)
    of = services.join(cmap, "device").select(F.col("service").cast("string").alias("node"), "cluster")
    edges = freq.select(F.lit(0).alias("scenario"), F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst"), F.col("freq").cast("double").alias("w"))
    nodes = edges.groupBy("scenario", F.col("dst").alias("node")).agg(F.sum("w").alias("s")).join(of, "node").select("scenario", F.col("cluster").alias("grp"), "node", "s")
    return nodes, edges, of


@query
def op_crossings(s, d):
    _, edges, of = _calls_as_scores(s, d)
    return exchange.crossings(edges, of).select("cluster", "src", "callee", "callee_cluster", "w")


@query
def op_mean_score(s, d):
    nodes, _, of = _calls_as_scores(s, d)
    return exchange.mean_score(nodes, of).select("cluster", r6("mean_s").alias("mean_s"))


@query
def op_messages(s, d):
    nodes, edges, of = _calls_as_scores(s, d)
    m = exchange.messages(exchange.crossings(edges, of), exchange.mean_score(nodes, of))
    return m.select("from_cluster", "to_cluster", "kind", r6("mean_s").alias("mean_s"), "crossing_w")


@query
def op_augment(s, d):
    """Nodes of clusters once linked clusters have joined them."""
    nodes, edges, of = _calls_as_scores(s, d)
    none = edges.where(F.lit(False)).select("scenario", F.lit(0).cast("long").alias("grp"), "src", "dst", "w")
    out, _ = exchange.augment(nodes, none, exchange.crossings(edges, of), exchange.mean_score(nodes, of))
    return out.select("grp", "node", r6("s").alias("s"))


@query
def op_combine(s, d):
    """Scores of nodes as seen by all clusters, each score a share of its cluster's total."""
    nodes, edges, of = _calls_as_scores(s, d)
    none = edges.where(F.lit(False)).select("scenario", F.lit(0).cast("long").alias("grp"), "src", "dst", "w")
    cross = exchange.crossings(edges, of)
    seen, _ = exchange.augment(nodes, none, cross, exchange.mean_score(nodes, of))
    ranking = scoring.share(seen, "s", "r", "scenario", "grp")
    return aggregate.combine(ranking, exchange.linked(cross)).select("node", r6("score").alias("score"))


@query
def op_influence(s, d):
    r = _decentral(s, d)
    return aggregate.influence(r.ranking, r.linked).withColumn("r", r6("r"))


def _nations(s, d):
    """Nations with region, calls received, and work: pairs of calls made."""
    f = wl_freq_nation(s, d)
    n = load(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("k"), F.col("n_regionkey").cast("int").alias("scenario"))
    got = f.groupBy(F.col("dst").alias("k")).agg(F.sum("freq").alias("r"))
    made = f.groupBy(F.col("src").alias("k")).agg(F.sum("freq").alias("t"))
    return n.join(got, "k", "left").join(made, "k", "left").select("scenario", F.col("k").alias("node"), F.coalesce("r", F.lit(0)).cast("double").alias("r"), F.coalesce("t", F.lit(0)).cast("double").alias("t"))


@query
def op_acc_mar_mrr(s, d):
    """Measures of a ranking: nations of each region by calls received, against the one with most customers."""
    final = ppr.rank(_nations(s, d).select("scenario", "node", "r"), ("scenario",))
    n = load(s, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_regionkey").cast("int").alias("scenario"))
    size = load(s, d, "customer").join(n, "c_nationkey").groupBy("scenario", F.col("c_nationkey").cast("long").alias("k")).agg(F.count("*").alias("n"))
    truth = size.groupBy("scenario").agg(F.max_by("k", F.struct("n", "k")).alias("root"))
    return evaluate.ranks(final, truth).agg(F.count("*").alias("scenarios"), *(r6(c).alias(n) for c, n in zip(evaluate.accuracy(), [f"acc_{k}" for k in evaluate.KS] + ["mar", "mrr"])))


@query
def op_time_reduction(s, d):
    """Reductions if each nation of a region works alone: the region's calls against those of its busiest nation."""
    t = _nations(s, d).groupBy("scenario").agg(F.sum("t").alias("t_c"), F.max("t").alias("t_d"))
    avg, total = evaluate.reductions()
    return t.agg(r6(avg).alias("avg_reduction"), r6(total).alias("total_reduction"))


# ---- localization on generated scenarios


def _runs(s, d):
    i = scenarios.build(s, d)
    sc = localize.score(i)
    return i, sc, localize.centralized(sc), localize.decentralized(i, sc)


def _decentral(s, d):
    i = scenarios.build(s, d)
    return localize.decentralized(i, localize.score(i))


MEASURES, REDUCTIONS = [*(f"acc_{k}" for k in evaluate.KS), "mar", "mrr"], ["avg_reduction", "total_reduction"]


def _rounded(columns, names):
    return [r6(c).alias(n) for c, n in zip(columns, names)]


def _summary(compared: DataFrame, *by: str) -> DataFrame:
    """Measures of both methods as rows."""
    out = None
    for name, rank in (("centralized", "rank_c"), ("decentralized", "rank_d")):
        a = compared.withColumn("rank", F.col(rank)).groupBy(*by).agg(F.count("*").alias("scenarios"), *_rounded(evaluate.accuracy(), MEASURES), *_rounded(evaluate.reductions(), REDUCTIONS)).withColumn("method", F.lit(name))
        out = a if out is None else out.unionByName(a)
    return out


@query
def loc_series(s, d):
    i = scenarios.build(s, d)
    return i.nodes.groupBy("metric").agg(F.count("*").alias("n"), r6(F.avg(F.element_at("v", -1))).alias("last"))


@query
def loc_flags(s, d):
    """Flagged series of services and calls."""
    n, e = localize.flags(scenarios.build(s, d))
    return n.select("scenario", F.col("node").alias("entity"), "metric").union(e.select("scenario", F.concat_ws(">", "src", "dst"), "metric"))


@query
def loc_triggers(s, d):
    """Incidents: the layers at which something is flagged, and how many series. Devices host one service each, so theirs are the services' once more."""
    i = scenarios.build(s, d)
    n, e = localize.flags(i)
    return localize.triggers(n, e, localize.device_flags(i)).select("scenario", F.array_join("layers", ",").alias("layers"), "n_flags")


@query
def score_node(s, d):
    return localize.score(scenarios.build(s, d)).nodes.withColumn("s", r6("s"))


@query
def score_node_local(s, d):
    """Scores as each cluster makes them: callers on calls inside its subgraph only."""
    i = scenarios.build(s, d)
    sc = localize.score(i)
    own, calls = subgraph.form(i.services, i.calls, i.cluster_map)
    return subgraph.populate(own, calls, sc.nodes, sc.parts, sc.edges)[0].withColumn("s", r6("s"))


@query
def score_edge(s, d):
    return localize.score(scenarios.build(s, d)).edges.withColumn("w", r6("w"))


@query
def score_rt_baseline(s, d):
    return localize.score(scenarios.build(s, d), scoring_by="rt").nodes.withColumn("s", r6("s"))


@query
def score_explain(s, d):
    """The three strongest terms of each service's score, metric pairs and callers."""
    n, e = localize.flags(scenarios.build(s, d))
    return scoring.explain(n, calls=scoring.call_influence(e, n)).withColumn("corr", r6("corr"))


@query
def loc_central(s, d):
    return localize.centralized(localize.score(scenarios.build(s, d))).final


@query
def loc_decentral(s, d):
    return _decentral(s, d).final


@query
def loc_messages(s, d):
    r = _decentral(s, d)
    return exchange.messages(r.cross, r.means).withColumns({"mean_s": r6("mean_s"), "crossing_w": r6("crossing_w")})


@query
def loc_decisions(s, d):
    """How linked scenarios were decided, and the winning cluster under consensus."""
    return _decentral(s, d).decision


@query
def loc_combined(s, d):
    r = _decentral(s, d)
    return aggregate.combine(r.ranking, r.linked).withColumn("score", r6("score"))


@query
def eval_accuracy(s, d):
    i, _, c, r = _runs(s, d)
    return _summary(localize.compare(i, c, r), "grp")


@query
def eval_breakdown(s, d):
    i, _, c, r = _runs(s, d)
    return _summary(localize.compare(i, c, r), "type", "grp")


@query
def eval_by_fault(s, d):
    i, _, c, r = _runs(s, d)
    return _summary(localize.compare(i, c, r), "fault")


@query
def op_rollup_breakdown(s, d):
    i, _, c, r = _runs(s, d)
    return localize.compare(i, c, r).rollup("type", "grp").agg(F.count("*").alias("n"), r6(F.avg("rank_d")).alias("mar"), F.grouping_id().alias("level"))


@query
def op_cube_fault(s, d):
    return scenarios.build(s, d).truth.cube("grp", "fault").agg(F.count("*").alias("n"))


@query
def eval_time_cost(s, d):
    """Work in edge visits: means and reductions by group, of the slowest cluster against the whole graph."""
    i, _, c, r = _runs(s, d)
    sums = [r6(F.avg("t_c")).alias("central_visits"), r6(F.avg("t_d")).alias("slowest_visits"), *_rounded(evaluate.reductions(), REDUCTIONS)]
    return localize.compare(i, c, r).groupBy("grp").agg(F.count("*").alias("scenarios"), *sums)


@query
def eval_learned_stand_in(s, d):
    """The learned stand-in beside both methods, on the scenarios that it was not fitted on."""
    i, sc, c, r = _runs(s, d)
    test = i.truth.where("scenario % 2 = 0")
    out = None
    for name, final in (("learned_stand_in", baselines.learned_stand_in(sc, i.truth)), ("centralized", c.final), ("decentralized", r.final)):
        a = evaluate.ranks(final, test).groupBy("grp").agg(F.lit(name).alias("method"), F.count("*").alias("scenarios"), *evaluate.accuracy())
        out = a if out is None else out.union(a)
    return out


@query
def eval_conflicts(s, d):
    return evaluate.conflict_rate(_decentral(s, d).decision).withColumn("conflict_rate", r6("conflict_rate"))


@query
def eval_communication(s, d):
    i = scenarios.build(s, d)
    r = localize.decentralized(i, localize.score(i))
    return evaluate.communication(exchange.messages(r.cross, r.means), i.nodes.select("scenario").union(i.edges.select("scenario")), scenarios.BINS)


@query
def eval_idle(s, d):
    r = _decentral(s, d)
    ready = r.ranking.select("scenario", F.col("grp").alias("cluster"), (F.col("n_nodes") + F.col("n_edges")).cast("double").alias("t")).distinct()
    return exchange.timeline(r.linked, ready)


@query
def eval_parallel_time(s, d):
    """Time of incidents in units of work, correlations and edge visits: the whole graph against clusters side by side, with waiting; by type."""
    i, sc, c, r = _runs(s, d)
    of = i.services.join(i.cluster_map, "device").select(F.col("service").alias("node"), F.col("cluster").cast("long").alias("cluster"))
    ready = checkpointed(localize.score_ready(sc, of))
    pairs = exchange.timeline(r.linked, ready.withColumnRenamed("grp", "cluster"))
    none = pairs.where(F.lit(False))
    tc = evaluate.parallel_time(c.ranking, localize.score_ready(sc), none).select("scenario", F.col("t").alias("t_c"))
    td = evaluate.parallel_time(r.ranking, ready, pairs).select("scenario", F.col("t").alias("t_d"), "total")
    both = exchange.propagation_type(i.truth, r.cross).join(tc, "scenario").join(td, "scenario")
    return both.groupBy("type").agg(F.count("*").alias("scenarios"), r6(F.avg("t_c")).alias("central"), r6(F.avg("t_d")).alias("parallel"), r6(F.avg("total")).alias("all_clusters"), *_rounded(evaluate.reductions(), REDUCTIONS))


SIZES = (10, 25, 50, 100, 250, 500, 1000)


@query
def eval_scaling(s, d):
    """Work against the number of services: suppliers folded into n services, calls received as scores; the whole graph, and the slowest of four clusters without exchange."""
    calls = checkpointed(wl_freq_supplier(s, d))
    most = load(s, d, "supplier").count()
    size = F.explode(F.array(*(F.lit(n) for n in SIZES if n <= most or n == SIZES[0])))
    e = calls.select(size.alias("scenario"), "src", "dst", "freq").select("scenario", (F.col("src") % F.col("scenario")).alias("src"), (F.col("dst") % F.col("scenario")).alias("dst"), "freq").where("src <> dst")
    e = checkpointed(e.groupBy("scenario", "src", "dst").agg(F.sum("freq").cast("double").alias("w")))
    nodes = e.groupBy("scenario", F.col("dst").alias("node")).agg(F.sum("w").alias("s"))
    one, part = F.lit(-1).cast("long").alias("grp"), lambda c: (F.col(c) % 4).alias("grp")
    central = ppr.solve_local(nodes.select("*", one), e.select("*", one))
    apart = ppr.solve_local(nodes.select("*", part("node")), e.where("src % 4 = dst % 4").select("*", part("src")))
    wc, wd = (evaluate.work(x).select("scenario", F.col("t_max").alias(n)) for x, n in ((central, "central_visits"), (apart, "slowest_visits")))
    edges = e.groupBy("scenario").agg(F.count("*").alias("edges"))
    return edges.join(wc, "scenario").join(wd, "scenario").select(F.col("scenario").alias("services"), "edges", "central_visits", "slowest_visits")


@query
def tune_tpe(s, d):
    """Trials of the Parzen search of the merge threshold, restart weight and stopping change: the objective is the MRR of even scenarios; odd ones are held out. Eight trials are one job."""
    i = scenarios.build(s, d)
    sc = localize.score(i)
    first = clustering.initial(i.services)
    w = checkpointed(clustering.weights(i.calls, i.services, first))
    total = clustering.threshold(w, 1.0)
    rows = []

    def objective(batch):
        maps = [clustering.merge_greedy(w, first, p["tau_rel"] * total) for p in batch]
        cmap = localize.cluster_copies(maps, i.truth)
        walks = s.createDataFrame([(k, p["alpha"], p["eps"]) for k, p in enumerate(batch)], "copy int, alpha double, eps double")
        walks = i.truth.select("scenario").crossJoin(F.broadcast(walks)).select((F.col("scenario") + localize.COPY * F.col("copy")).cast("int").alias("scenario"), "alpha", "eps")
        r = localize.decentralized(i, localize.replicated(sc, len(batch)), cluster_map=cmap, walk=checkpointed(walks))
        truth = i.truth.select("scenario", "root").withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(len(batch) - 1)))).select((F.col("scenario") + localize.COPY * F.col("copy")).cast("int").alias("scenario"), "root")
        got = localize.copy_of(evaluate.ranks(r.final, truth))
        held = F.col("scenario") % 2 == 1
        mrr = {x.copy: x for x in got.groupBy("copy").agg(F.avg(F.when(~held, 1 / F.col("rank"))).alias("fit"), F.avg(F.when(held, 1 / F.col("rank"))).alias("held")).collect()}  # a row for each trial
        many = {x.copy: x.n for x in localize.copy_of(cmap).groupBy("copy").agg(F.countDistinct("cluster").alias("n")).collect()}
        rows.extend((p["tau_rel"], p["alpha"], p["eps"], many[k], mrr[k].fit, mrr[k].held) for k, p in enumerate(batch))
        return [mrr[k].fit for k in range(len(batch))]

    tune.tpe(objective, {"tau_rel": (0.002, 0.05, "log"), "alpha": (0.1, 0.9, "lin"), "eps": (1e-8, 1e-3, "log")}, trials=24)
    return s.createDataFrame([(k, *x) for k, x in enumerate(rows)], "trial int, tau_rel double, alpha double, eps double, clusters long, mrr_fit double, mrr_held double")


@query
def eval_variants(s, d):
    """Accuracy and work of every variant and baseline over all scenarios."""
    i, sc, c, r = _runs(s, d)
    of = {"centralized": c, "decentralized": r}
    of["global_scores"] = localize.decentralized(i, sc, scope="global")
    of["no_exchange"] = localize.decentralized(i, sc, use_exchange=False)
    of["always_aggregate"] = localize.decentralized(i, sc, aggregate_mode="always")
    of["never_aggregate"] = localize.decentralized(i, sc, aggregate_mode="consensus")
    of["renormalized"] = localize.decentralized(i, sc, renormalize=True)
    of["flagged_mean"] = localize.decentralized(i, sc, flagged_only=True)
    of["two_rounds"] = localize.decentralized(i, sc, rounds=2)
    for name, how in {"rt_scores": {"scoring_by": "rt"}, "metric_part": {"parts": ("metric",)}, "edge_part": {"parts": ("edge",)}, "full_pairs": {"pairs": "full"}, "self_pairs": {"pairs": "self"}, "spearman": {"kind": "spearman"}, "r2": {"kind": "r2"}, "cocluster": {"grouping": "cocluster"}}.items():
        other = localize.score(i, **how)
        of[f"central_{name}"] = localize.centralized(other)
        if name in ("rt_scores", "cocluster"):
            of[f"decentral_{name}"] = localize.decentralized(i, other)
    finals = {n: (x.final, evaluate.work(x.ranking).select("scenario", "t_max")) for n, x in of.items()}
    for kind in ("pagerank", "in_degree", "score"):
        finals[f"central_{kind}"] = (baselines.centrality(sc, kind), None)
    # cluster maps as copies of the scenarios, in one run
    names = ["per_device", "one_cluster", "random_clusters", "per_scenario"]
    maps = [clustering.initial(i.services), i.cluster_map.withColumn("cluster", F.lit(0).cast("long")), i.cluster_map.withColumn("cluster", F.floor(F.col("device") / 9).cast("long")), scenarios.scenario_clusters(s, d)]
    copies = localize.decentralized(i, localize.replicated(sc, len(maps)), cluster_map=localize.cluster_copies(maps, i.truth))
    final, cost = checkpointed(localize.copy_of(copies.final)), checkpointed(localize.copy_of(evaluate.work(copies.ranking).select("scenario", "t_max")))
    for k, name in enumerate(names):
        finals[name] = (final.where(F.col("copy") == k).drop("copy"), cost.where(F.col("copy") == k).drop("copy"))
    out = None
    for name, (final, cost) in finals.items():
        got = evaluate.ranks(final, i.truth)
        got = got.join(cost, "scenario", "left") if cost is not None else got.withColumn("t_max", F.lit(None).cast("double"))
        a = got.agg(F.lit(name).alias("variant"), *_rounded(evaluate.accuracy(), MEASURES), r6(F.avg("t_max")).alias("visits"))
        out = a if out is None else out.union(a)
    return out


@query
def op_variant_diff(s, d):
    """Scenarios whose first answer differs between the two methods."""
    _, _, c, r = _runs(s, d)
    top = lambda x: x.where("rank = 1").select("scenario", "node")
    return top(c.final).exceptAll(top(r.final))


@query
def stream_series(s, d):
    """Events replayed as a stream; the daily series at the end, kept by an aggregation's state."""
    from edgeloc.streaming import detect

    return detect.run_once(detect.daily_series(detect.event_stream(s, d)), "edgeloc_stream_series")


@query
def stream_detect(s, d):
    """Flags of event types after a replay; the last update of each."""
    from edgeloc.streaming import detect

    samples = detect.event_stream(s, d).select(F.col("event_type").alias("entity"), (F.col("value") / 1000).alias("value"), "ts", "event_id")
    out = detect.run_once(detect.flags(samples, 0.05), "edgeloc_stream_detect", "update")
    return out.groupBy("entity").agg(F.max("n_features").alias("n_features"), F.bool_or("is_anomalous").alias("is_anomalous"))
