"""The localizer against plain numpy on random incidents: scores, exchange, walks, decision and final ranking, written apart from the engine."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgeloc.operators import aggregate, birch, clustering, evaluate, exchange, localize, ppr, subgraph
from edgeloc.sources.scenarios import Inputs

T, N = 24, 9
METRICS, PCT = ("a", "b", "c"), ("p50", "p90", "p99")
CLUSTER = {str(k): k // 3 for k in range(N)}


def incidents(seed=5, scenarios=16):
    rng = np.random.default_rng(seed)
    calls = sorted({(int(a), int(b)) for a, b in rng.integers(0, N, (26, 2)) if a != b})
    nodes, edges = {}, {}
    for s in range(scenarios):
        shock = np.where(np.arange(T) >= 12, 1 + np.arange(T) % 3, 0)
        hot = set(rng.choice(N, 1 + s % 4, replace=False).tolist())
        for n in range(N):
            for m in METRICS:
                if n in hot and rng.random() < 0.8:
                    nodes[s, str(n), m] = 1 + rng.random(T) * 0.3 + shock * rng.uniform(2, 6)
                else:
                    nodes[s, str(n), m] = 1 + rng.random(T) * 0.02
        for a, b in calls:
            for m in PCT:
                edges[s, str(a), str(b), m] = 1 + rng.random(T) * 0.3 + (shock * rng.uniform(2, 6) if b in hot and rng.random() < 0.8 else 0)
    return calls, nodes, edges


def flagged(v, beta=0.07):
    z = v / np.sqrt((v * v).sum())
    return any(z[: k + 1].std() > beta for k in range(len(z)))


def corr(x, y):
    return abs(np.corrcoef(x, y)[0, 1])


def plain(calls, nodes, edges, scope, clusters):
    """{scenario: ranked services} of the decentralized method, {scenario: mode}, and the scores that it used."""
    out, modes, scores = {}, {}, {}
    for s in sorted({k[0] for k in nodes}):
        a = {}
        for (x, n, m), v in nodes.items():
            if x == s and flagged(v):
                a.setdefault(n, {})[m] = v
        b = {}
        for (x, p, q, m), v in edges.items():
            if x == s and flagged(v):
                b.setdefault((p, q), {})[m] = v
        touched = set(a) | {n for e in b for n in e}
        pairs = lambda d: sum(corr(x, y) for x, y in itertools.combinations(d.values(), 2))
        score = {}
        for n in touched:
            score[n] = pairs(a.get(n, {}))
            for (p, q), d in b.items():
                if q == n and "p90" in d and n in a and (scope == "global" or clusters[p] == clusters[n]):
                    score[n] += max(corr(d["p90"], x) for x in a[n].values())
        scores[s] = score
        w = {e: pairs(d) for e, d in b.items()}
        groups = sorted({clusters[n] for n in touched})
        cross = {e: x for e, x in w.items() if clusters[e[0]] != clusters[e[1]]}
        linked = {(clusters[p], clusters[q]) for p, q in cross} | {(clusters[q], clusters[p]) for p, q in cross}
        size = lambda g: sum(c == g for c in clusters.values())
        mean = {g: sum(x for n, x in score.items() if clusters[n] == g) / size(g) for g in groups}
        ranks = {}
        for g in groups:
            v = {n: score[n] for n in touched if clusters[n] == g} | {f"cluster:{h}": mean.get(h, 0.0) for i, h in linked if i == g}
            e = {k: x for k, x in w.items() if clusters[k[0]] == clusters[k[1]] == g}
            for (p, q), x in cross.items():
                if clusters[p] == g:
                    k = (p, f"cluster:{clusters[q]}")
                    e[k] = e.get(k, 0) + x
                if clusters[q] == g:
                    k = (f"cluster:{clusters[p]}", q)
                    e[k] = e.get(k, 0) + x
            names = sorted(v)
            pers = np.array([v[n] for n in names])
            pers = pers / pers.sum() if pers.sum() else np.full(len(names), 1 / len(names))
            m = np.zeros((len(names), len(names)))
            for (p, q), x in e.items():
                m[names.index(p), names.index(q)] += x
            total = m.sum(1)
            p = np.divide(m, total[:, None], out=np.zeros_like(m), where=total[:, None] > 0)
            p[total == 0] = pers  # dangling mass goes to the personalization
            r = 0.5 * np.linalg.solve(np.eye(len(names)) - 0.5 * p.T, pers)
            ranks[g] = dict(zip(names, r))
        who = sorted({g for g, _ in linked})
        own = {g: {n: x for n, x in ranks[g].items() if not n.startswith("cluster:")} for g in groups}
        winner, combined = None, {}
        if who:
            top = {g: min(ranks[g], key=lambda n: (-round(ranks[g][n], 9), n)) for g in who}
            locals_ = [g for g in who if not top[g].startswith("cluster:")]
            if len(locals_) == 1 and all(top[g] == f"cluster:{locals_[0]}" for g in who if g != locals_[0]):
                winner = locals_[0]
            modes[s] = "consensus" if winner is not None else "conflict" if len(locals_) > 1 else "pointing"
            for g in who:
                for n, x in own[g].items():
                    combined[n] = combined.get(n, 0) + x / len(who)
                for h in who:
                    mass = ranks[g].get(f"cluster:{h}")
                    for n, x in own[h].items() if mass is not None else ():
                        combined[n] = combined.get(n, 0) + mass * x / len(who)
        all_mass = sum(score.values())
        final = []
        for g in groups:
            share = sum(score[n] for n in own[g]) / all_mass if all_mass else 1
            for n, x in own[g].items():
                tier = 0 if g == winner else 1 if n in combined else 2
                final.append((tier, -round(combined[n] if tier == 1 else x * share, 9), n))
        out[s] = [n for _, _, n in sorted(final)]
    return out, modes, scores


@pytest.fixture(scope="module")
def case(spark):
    calls, nodes, edges = incidents()
    services = spark.createDataFrame([(n, int(n)) for n in CLUSTER], "service string, device long")
    cmap = spark.createDataFrame([(int(n), c) for n, c in CLUSTER.items()], "device long, cluster long")
    freq = spark.createDataFrame([(str(a), str(b), 1) for a, b in calls], "src string, dst string, freq long")
    nf = spark.createDataFrame([(s, n, m, v.tolist()) for (s, n, m), v in nodes.items()], "scenario int, node string, metric string, v array<double>")
    ef = spark.createDataFrame([(s, a, b, m, v.tolist()) for (s, a, b, m), v in edges.items()], "scenario int, src string, dst string, metric string, v array<double>")
    i = Inputs(services, freq, cmap, nf, ef, None)
    return (calls, nodes, edges), i, localize.score(i)


@pytest.mark.parametrize("scope", ["subgraph", "global"])
def test_whole_method_equals_numpy(case, scope):
    made, i, sc = case
    want, modes, scores = plain(*made, scope, CLUSTER)
    r = localize.decentralized(i, sc, scope=scope, eps=1e-12)
    got = {}
    for x in r.final.orderBy("scenario", "rank").collect():
        got.setdefault(x.scenario, []).append(x.node)
    assert got == want and len(set(map(str, want.values()))) > 5
    assert {x.scenario: x.mode for x in r.decision.collect()} == modes and len(set(modes.values())) > 1


def test_no_score_reads_a_caller_outside_its_subgraph(case):
    made, i, sc = case
    own, calls = subgraph.form(i.services, i.calls, i.cluster_map)
    nodes, inner, cross = subgraph.populate(own, calls, sc.nodes, sc.parts, sc.edges)
    scores = plain(*made, "subgraph", CLUSTER)[2]
    assert {(r.scenario, r.node): r.s for r in nodes.collect()} == pytest.approx({(s, n): x for s, d in scores.items() for n, x in d.items()})
    assert not inner.join(cross.select("scenario", "src", F.col("callee").alias("dst")), ["scenario", "src", "dst"]).count()
    # shadows stand in the caller's cluster only, nothing leaves them, and every call is kept once
    assert calls.count() == i.calls.count() and not calls.where("src like 'shadow:%'").count()
    shadows = own.where("is_shadow").select("cluster", F.col("node").alias("dst"))
    assert calls.where("crosses").join(shadows, ["cluster", "dst"], "left_anti").count() == 0 and own.where("is_shadow and cluster = remote_cluster").count() == 0


def test_one_cluster_is_the_centralized_run(case):
    _, i, sc = case
    one = i.cluster_map.withColumn("cluster", F.lit(0).cast("long"))
    rows = lambda df: sorted(map(tuple, df.select("scenario", "node", "rank").collect()))
    assert rows(localize.decentralized(i, sc, cluster_map=one).final) == rows(localize.centralized(sc).final)


def test_clusters_of_each_scenario_and_copies(case):
    """Half of the scenarios with other clusters, in one run, equal two runs; so do copies."""
    made, i, sc = case
    other = {n: int(n) % 2 for n in CLUSTER}
    second = i.cluster_map.withColumn("cluster", (F.col("device") % 2).cast("long"))
    truth = sc.nodes.select("scenario").distinct()
    copies = localize.decentralized(i, localize.replicated(sc, 2), cluster_map=localize.cluster_copies([i.cluster_map, second], truth), eps=1e-12)
    got = {}
    for x in localize.copy_of(copies.final).orderBy("scenario", "rank").collect():
        got.setdefault((x.copy, x.scenario), []).append(x.node)
    assert got == {(k, s): v for k, c in enumerate((CLUSTER, other)) for s, v in plain(*made, "subgraph", c)[0].items()}


def test_switches_change_the_answer(spark):
    """A conflict in which combining, not combining and renormalizing each put another service first."""
    rows = [(0, 1, "m1", 0.40), (0, 1, "m2", 0.05), (0, 1, "cluster:2", 0.55), (0, 2, "m3", 0.45), (0, 2, "m4", 0.30), (0, 2, "cluster:1", 0.25)]
    ranking = spark.createDataFrame([(*r, 1 + sum(x[1] == r[1] and x[3] > r[3] for x in rows)) for r in rows], "scenario int, grp long, node string, r double, rank int")
    linked = spark.createDataFrame([(0, 1, 2), (0, 2, 1)], "scenario int, grp long, other long")
    decision = aggregate.decide(ranking, linked)
    assert decision.first().mode == "consensus" and decision.first().winner == 2
    mass = spark.createDataFrame([(0, 1, 3.0), (0, 2, 1.0)], "scenario int, grp long, t double")
    none = decision.withColumns({"mode": F.lit("conflict"), "winner": F.lit(None).cast("long")})
    order = lambda *a, **k: [r.node for r in aggregate.final_ranking(ranking, linked, *a, mass, **k).orderBy("rank").collect()]
    assert order(decision)[0] == "m3" and order(none, mode="consensus")[0] == "m1"
    assert order(decision, mode="always")[0] == "m3"  # (.45 + .55 * .45) / 2 against (.40 + .25 * .40) / 2
    combined = lambda **k: {r.node: round(r.score, 6) for r in aggregate.combine(ranking, linked, **k).collect()}
    assert combined() == {"m1": 0.25, "m2": 0.03125, "m3": 0.34875, "m4": 0.2325} and sum(combined(renormalize=True).values()) == pytest.approx(1.0)


def test_decisions_by_hand(spark):
    def decide(*rows):
        ranking = spark.createDataFrame([(0, g, n, 1) for g, n in rows], "scenario int, grp long, node string, rank int")
        linked = spark.createDataFrame([(0, g, rows[(k + 1) % len(rows)][0]) for k, (g, _) in enumerate(rows)], "scenario int, grp long, other long")
        x = aggregate.decide(ranking, linked).first()
        return x["mode"], x["winner"]

    assert decide((1, "m1"), (2, "cluster:1")) == ("consensus", 1)
    assert decide((1, "m1"), (2, "m2")) == ("conflict", None)
    assert decide((1, "cluster:2"), (2, "cluster:1")) == ("pointing", None)
    assert decide((1, "m1"), (2, "cluster:3"), (3, "cluster:1")) == ("pointing", None)


def test_timeline_and_parallel_time(spark):
    links = spark.createDataFrame([(0, 1, 2), (0, 2, 1)], "scenario int, grp long, other long")
    ready = spark.createDataFrame([(0, 1, 3.0), (0, 2, 5.0), (0, 3, 9.0)], "scenario int, cluster long, t double")
    x = exchange.timeline(links, ready, notice=0.5, delay=0.25).first()
    assert (x.wait_sent, x.wait_received, x.ready, x.idle) == (0.5, 0.75, 5.25, 2.0)
    ranking = spark.createDataFrame([(0, 1, "a", 2, 3, 1), (0, 2, "b", 1, 4, 2), (0, 3, "c", 1, 1, 0)], "scenario int, grp long, node string, iterations int, n_nodes int, n_edges int")
    t = evaluate.parallel_time(ranking, ready.withColumnRenamed("cluster", "grp"), exchange.timeline(links, ready, delay=0.25)).first()
    assert (t.t, t.total) == (5.25 + 8, 3 + 8 + 5 + 6 + 9 + 1)


def dense(s, e, n, dangling):
    m = np.zeros((n, n))
    for a, b, w in e:
        m[a, b] += w
    total = m.sum(1)
    p = np.divide(m, total[:, None], out=np.zeros_like(m), where=total[:, None] > 0)
    s = s / s.sum()
    if dangling != "drop":
        p[total == 0] = s if dangling == "personalized" else np.eye(n)[total == 0]
        return 0.5 * np.linalg.solve(np.eye(n) - 0.5 * p.T, s)
    r = s
    for _ in range(200):
        r = 0.5 * p.T @ r + 0.5 * s
        r = r / r.sum()
    return r


def test_walks_equal_the_dense_solution(spark):
    rng = np.random.default_rng(3)
    for n in (2, 7, 15):
        s = rng.random(n)
        e = [(int(a), int(b), float(w)) for a, b, w in zip(rng.integers(0, n, 2 * n), rng.integers(0, n - 1, 2 * n), rng.random(2 * n))]
        src, dst, w = (np.array(x) for x in zip(*e))
        for how in ("personalized", "loop", "drop"):
            got = ppr.iterate(s, src, dst, w, 0.5, 1e-13, dangling=how)[0]
            assert got == pytest.approx(dense(s, e, n, how), abs=1e-9)
        cold, steps, _ = ppr.iterate(s, src, dst, w, 0.5, 1e-10)
        warm, fewer, _ = ppr.iterate(s, src, dst, w, 0.5, 1e-10, start=cold)
        assert warm == pytest.approx(cold, abs=1e-8) and fewer < steps
    nodes = spark.createDataFrame([(k, str(v), float(x)) for k in (0, 1) for v, x in enumerate(s)], "g int, node string, s double")
    edges = spark.createDataFrame([(k, str(a), str(b), x * (1 + k * a)) for k in (0, 1) for a, b, x in e] + [(0, "gone", "0", 5.0)], "g int, src string, dst string, w double")
    want = {(k, str(v)): x for k in (0, 1) for v, x in enumerate(dense(s, [(a, b, x * (1 + k * a)) for a, b, x in e], n, "personalized"))}
    told = lambda df: {(r.g, r.node): r.r for r in df.collect()}
    assert told(ppr.solve_local(nodes, edges, ("g",), eps=1e-12)) == pytest.approx(want, abs=1e-9)
    assert told(ppr.solve_local(nodes, edges, ("g",), eps=1e-9, max_edges=1)) == pytest.approx(want, abs=1e-7)  # all groups go the other way
    assert told(ppr.solve_steps(nodes, edges, 0.5, 30, ("g",))) == pytest.approx(want, abs=1e-7)


def test_merges_of_random_graphs_agree(spark):
    rng, rows, taus, want = np.random.default_rng(11), [], {}, {}
    for k in range(40):
        n = int(rng.integers(3, 10))
        w = {(a, b): int(rng.integers(1, 9)) for a in range(n) for b in range(a + 1, n) if rng.random() < 0.6}
        taus[k] = float(rng.integers(2, 12))
        rows += [(k, a, b, x, taus[k]) for (a, b), x in w.items()]
        label, left = {d: d for d in range(10)}, dict(w)
        while left and max(left.values()) > taus[k]:
            a, b = max(left, key=lambda p: (left[p], p))
            label = {d: a if c == b else c for d, c in label.items()}
            new = {}
            for (p, q), x in left.items():
                p, q = (a if p == b else p), (a if q == b else q)
                if p != q:
                    new[min(p, q), max(p, q)] = new.get((min(p, q), max(p, q)), 0) + x
            left = new
        want |= {(k, d): min(x for x in label if label[x] == label[d]) for d in label}
    w = spark.createDataFrame(rows, "g int, c1 long, c2 long, w long, tau double")
    first = spark.createDataFrame([(k, d, d) for k in range(40) for d in range(10)], "g int, device long, cluster long")
    got = clustering.merge_parallel(w, first, None, keys=("g",))
    assert {(r.g, r.device): r.cluster for r in got.collect()} == want
    one = clustering.merge_greedy(w.where("g = 3").select("c1", "c2", "w"), first.where("g = 3").select("device", "cluster"), taus[3])
    assert {(3, r.device): r.cluster for r in one.collect()} == {k: v for k, v in want.items() if k[0] == 3}
    services = first.where("g = 3").select(F.col("device").alias("service"), "device")
    assert clustering.validate(services, one).count() == 0 and clustering.validate(services, one.where("device > 0")).count() == 1


def test_flag_is_a_prefix_beyond_beta(spark):
    x = np.random.default_rng(1).normal(0, 0.06, (200, 20))
    df = spark.createDataFrame([(k, r.tolist()) for k, r in enumerate(x)], "k int, v array<double>")
    want = {k: any(r[: t + 1].std() > 0.07 for t in range(20)) for k, r in enumerate(x)}
    assert {r.k: r.is_anomalous for r in birch.detect(df).collect()} == want and 20 < sum(want.values()) < 180
