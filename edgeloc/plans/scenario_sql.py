"""DuckDB SQL for the generated scenarios: generator, clusters, flags, scores, walks, exchange, aggregation and measures, rebuilt apart from the engine.

Every function returns common table expressions; `statement` joins them under one WITH RECURSIVE. A flag needs no fold here: a series has a second
feature as soon as, and only if, the values up to some bin have a deviation above beta. Walks are unrolled: at a restart weight of 0.5 the change falls
below 1e-6 within 22 steps.
"""

from __future__ import annotations

SPANS = """spans AS (SELECT l_orderkey AS trace, l_suppkey AS service, CAST(s_nationkey AS BIGINT) AS device, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice FROM lineitem JOIN supplier ON s_suppkey = l_suppkey),
ncalls AS (SELECT trace, a, b FROM (SELECT trace, service, device AS a, lead(service) OVER w AS dst, lead(device) OVER w AS b FROM spans
  WINDOW w AS (PARTITION BY trace ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice)) WHERE service <> dst AND a <> b)"""
THIN = "thin AS MATERIALIZED (SELECT a AS src, b AS dst, count(*) AS freq FROM ncalls WHERE a % 3 = b % 3 OR trace % 128 = 0 GROUP BY 1, 2)"
FULL = "thin AS MATERIALIZED (SELECT a AS src, b AS dst, count(*) AS freq FROM ncalls GROUP BY 1, 2)"
ALPHA, EPS, BETA, STEPS = 0.5, 1e-6, 0.07, 23


def statement(parts: list[str], select: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n" + select


def clusters(tau: float = 0.01, calls: str = "thin", key: str = "0", rounds: int = 6) -> list[str]:
    """cmap(k, device, cluster): rounds in which all pairs above the threshold are contracted to their closure, and weights add up. key is the graph that a call belongs to."""
    out = [
        f"w0 AS MATERIALIZED (SELECT {key} AS k, least(src, dst) AS c1, greatest(src, dst) AS c2, sum(freq)::DOUBLE AS w FROM {calls} GROUP BY 1, 2, 3)",
        f"tau AS MATERIALIZED (SELECT k, {tau} * sum(w) AS tau FROM w0 GROUP BY 1)",
        "m0 AS (SELECT k, CAST(n_nationkey AS BIGINT) AS device, CAST(n_nationkey AS BIGINT) AS cluster FROM nation, tau)",
    ]
    for n in range(1, rounds + 1):
        b = n - 1
        out += [
            f"h{n} AS MATERIALIZED (SELECT k, c1 AS x, c2 AS y FROM w{b} JOIN tau USING (k) WHERE w > tau UNION ALL SELECT k, c2, c1 FROM w{b} JOIN tau USING (k) WHERE w > tau)",
            f"z{n} AS (SELECT k, x, y FROM h{n} UNION SELECT z{n}.k, z{n}.x, h{n}.y FROM z{n} JOIN h{n} ON z{n}.k = h{n}.k AND z{n}.y = h{n}.x)",
            f"l{n} AS MATERIALIZED (SELECT k, x AS c, least(x, min(y)) AS up FROM z{n} GROUP BY 1, 2)",
            f"m{n} AS MATERIALIZED (SELECT m.k, device, coalesce(up, cluster) AS cluster FROM m{b} m LEFT JOIN l{n} l ON l.k = m.k AND l.c = m.cluster)",
            f"w{n} AS MATERIALIZED (SELECT k, least(x, y) AS c1, greatest(x, y) AS c2, sum(w) AS w FROM (SELECT w.k, coalesce(p.up, c1) AS x, coalesce(q.up, c2) AS y, w FROM w{b} w LEFT JOIN l{n} p ON p.k = w.k AND p.c = c1 LEFT JOIN l{n} q ON q.k = w.k AND q.c = c2) WHERE x <> y GROUP BY 1, 2, 3)",
        ]
    return [*out, f"cmap AS MATERIALIZED (SELECT * FROM m{rounds})"]


GENERATOR = [
    "ranked AS (SELECT src, dst, src % 3 = dst % 3 AS same, row_number() OVER (PARTITION BY src, src % 3 = dst % 3 ORDER BY freq DESC, dst) AS k FROM thin)",
    "g AS MATERIALIZED (SELECT src AS a, dst AS b, row_number() OVER (ORDER BY src, same DESC, k) - 1 AS id FROM ranked WHERE k <= CASE WHEN same THEN 3 ELSE 1 END)",
    "sc AS MATERIALIZED (SELECT s, CASE WHEN s < 146 THEN 'HH' ELSE 'SH' END AS grp, ['cpu', 'memory', 'latency', 'loss', 'duplication', 'corruption', 'disorder', 'delay', 'jitter'][s % 9 + 1] AS fault, (11 * s + 5) % 25 AS root, s % 4 = 0 AS far FROM (SELECT CAST(unnest(range(0, 383)) AS INT) AS s))",
    "l_1 AS MATERIALIZED (SELECT s, a, id, root FROM sc JOIN g ON b = root WHERE far OR a % 3 = b % 3)",
    "f_1 AS MATERIALIZED (SELECT DISTINCT s, a AS node FROM l_1)",
    "l_2 AS MATERIALIZED (SELECT s, a, id, root FROM f_1 JOIN sc USING (s) JOIN g ON b = node WHERE far OR a % 3 = b % 3)",
    "f_2 AS MATERIALIZED (SELECT DISTINCT s, a AS node FROM l_2 WHERE a <> root EXCEPT SELECT s, node FROM f_1)",
    "factor AS MATERIALIZED (SELECT s, root AS node, 8.0 AS a, 4 AS many, 0 AS turn FROM sc UNION ALL SELECT s, node, 4.8, 3, node FROM f_1 UNION ALL SELECT s, node, 2.9, 2, node FROM f_2)",
    "odd AS (SELECT s, q, (7 * s + 13 * q + 3) % 25 AS node FROM sc, (SELECT unnest([0, 1]) AS q))",
    """hit AS MATERIALIZED (SELECT s, e, j, max(ramp) AS ramp, max(square) AS square FROM (
      SELECT s, node AS e, (s % 9 + k + turn) % 6 AS j, a AS ramp, 0.0 AS square FROM factor, (SELECT unnest(range(0, 4)) AS k) WHERE k < many
      UNION ALL SELECT s, 100 + id, m, 4.8, 0.0 FROM l_1, (SELECT unnest([0, 1, 2]) AS m) UNION ALL SELECT s, 100 + id, m, 2.9, 0.0 FROM l_2, (SELECT unnest([0, 1, 2]) AS m)
      UNION ALL SELECT s, node, (s + q + k) % 6, 0.0, 3.0 FROM odd ANTI JOIN factor USING (s, node), (SELECT unnest([0, 1, 2]) AS k)) GROUP BY 1, 2, 3)""",
    "top AS MATERIALIZED (SELECT quantile_cont(value, 0.95) AS top, count(*) AS n FROM events)",
    "u AS MATERIALIZED (SELECT row_number() OVER (ORDER BY event_id, value) - 1 AS i, least(value, top) / top AS x FROM events, top)",
    "ent AS MATERIALIZED (SELECT e, j FROM (SELECT unnest(range(0, 25)) AS e), (SELECT unnest(range(0, 6)) AS j) UNION ALL SELECT 100 + id, j FROM g, (SELECT unnest(range(0, 3)) AS j))",
    "place AS MATERIALIZED (SELECT s, e, j, t, (7919 * s + 131 * e + 17 * j + t) % n AS i FROM sc, ent, (SELECT unnest(range(0, 40)) AS t), top)",
    """series AS MATERIALIZED (SELECT s, e, j, t, (1 + x) * (1 + CASE WHEN t >= 20 THEN coalesce(ramp, 0) * (1 + (t % 5) / 5.0::DOUBLE) + coalesce(square, 0) * ((t // 5) % 2) ELSE 0 END) AS v
      FROM place JOIN u USING (i) LEFT JOIN hit USING (s, e, j))""",
]
FLAGS = [
    "unit AS (SELECT s, e, j, t, v, v / sqrt(sum(v * v) OVER (PARTITION BY s, e, j)) AS z FROM series)",
    f"""flagged AS MATERIALIZED (SELECT s, e, j FROM (SELECT s, e, j, stddev_pop(z) OVER (PARTITION BY s, e, j ORDER BY t ROWS UNBOUNDED PRECEDING) AS d FROM unit) GROUP BY 1, 2, 3 HAVING max(d) > {BETA})""",
    "fs AS MATERIALIZED (SELECT s, e, j, t, v FROM series SEMI JOIN flagged USING (s, e, j))",
    "nf AS (SELECT s, e, j FROM flagged WHERE e < 100)",
    "ef AS (SELECT f.s, f.j, g.a, g.b, f.e FROM flagged f JOIN g ON f.e = 100 + g.id)",
]
#: parts(s, node, src, x): a node's own metrics, then its callers; es: calls' scores.
SCORES = [
    "pairs AS MATERIALIZED (SELECT p.s, p.e, p.j AS j1, q.j AS j2, abs(corr(p.v, q.v)) AS r FROM fs p JOIN fs q ON p.s = q.s AND p.e = q.e AND p.t = q.t AND p.j < q.j GROUP BY ALL)",
    "own AS (SELECT s, e, coalesce(sum(r), 0) AS x FROM flagged LEFT JOIN (SELECT s, e, j1 AS j, sum(r) AS r FROM pairs GROUP BY ALL) USING (s, e, j) GROUP BY 1, 2)",
    "best AS MATERIALIZED (SELECT s, a, b, max(r) AS x FROM (SELECT c.s, g.a, g.b, m.j, abs(corr(c.v, m.v)) AS r FROM fs c JOIN g ON c.e = 100 + g.id JOIN fs m ON m.s = c.s AND m.e = g.b AND m.t = c.t WHERE c.j = 1 GROUP BY ALL) GROUP BY ALL)",
    "parts AS MATERIALIZED (SELECT s, e AS node, NULL::BIGINT AS src, x FROM own WHERE e < 100 UNION ALL SELECT s, b, a, x FROM best)",
    "es AS MATERIALIZED (SELECT s, a, b, x AS w FROM own JOIN g ON e = 100 + id)",
    "seen AS MATERIALIZED (SELECT s, e AS node FROM nf UNION SELECT s, a FROM ef UNION SELECT s, b FROM ef)",
    "scored AS MATERIALIZED (SELECT s, node, coalesce(sum(x), 0) AS x FROM seen LEFT JOIN parts USING (s, node) GROUP BY 1, 2)",
]


def walk(p: str, nodes: str, edges: str, steps: int = STEPS) -> list[str]:
    """{p}rank(s, grp, node, r, rank, its, nn, ne) from nodes(s, grp, node, x) and edges(s, grp, src, dst, w); names are text."""
    out = [
        f"{p}n AS MATERIALIZED (SELECT s, grp, node, CASE WHEN sum(x) OVER y > 0 THEN x / sum(x) OVER y ELSE 1.0::DOUBLE / count(*) OVER y END AS x, count(*) OVER y AS nn FROM {nodes} WINDOW y AS (PARTITION BY s, grp))",
        f"{p}e AS MATERIALIZED (SELECT e.* FROM {edges} e JOIN {p}n a ON a.s = e.s AND a.grp = e.grp AND a.node = e.src JOIN {p}n b ON b.s = e.s AND b.grp = e.grp AND b.node = e.dst)",
        f"{p}t AS MATERIALIZED (SELECT s, grp, src, sum(w) AS t FROM {p}e GROUP BY 1, 2, 3 HAVING sum(w) > 0)",
        f"{p}p AS MATERIALIZED (SELECT s, grp, src, dst, w / t AS p FROM {p}e JOIN {p}t USING (s, grp, src))",
        f"{p}0 AS (SELECT s, grp, node, x AS r, 0 AS k, NULL::DOUBLE AS d FROM {p}n)",
    ]
    for k in range(1, steps + 1):
        q = f"{p}{k - 1}"
        out.append(f"""{p}{k} AS MATERIALIZED (SELECT s, grp, node, {ALPHA} * (coalesce(m, 0) + coalesce(o, 0) * x) + {1 - ALPHA} * x AS r, {k} AS k, abs({ALPHA} * (coalesce(m, 0) + coalesce(o, 0) * x) + {1 - ALPHA} * x - q.r) AS d
          FROM {p}n JOIN {q} q USING (s, grp, node) LEFT JOIN (SELECT s, grp, dst AS node, sum(r * p) AS m FROM {q} JOIN {p}p USING (s, grp) WHERE node = src GROUP BY ALL) USING (s, grp, node)
          LEFT JOIN (SELECT s, grp, sum(r) AS o FROM (SELECT s, grp, node AS src, r FROM {q}) ANTI JOIN {p}t USING (s, grp, src) GROUP BY ALL) USING (s, grp))""")
    every = " UNION ALL ".join(f"SELECT * FROM {p}{k}" for k in range(1, steps + 1))
    return [
        *out,
        f"{p}all AS MATERIALIZED ({every})",
        f"{p}its AS (SELECT s, grp, min(k) AS its FROM (SELECT s, grp, k, sum(d) AS d FROM {p}all GROUP BY ALL) WHERE d < {EPS} GROUP BY ALL)",
        f"{p}ne AS (SELECT s, grp, count(*) AS ne FROM {p}e GROUP BY ALL)",
        f"""{p}rank AS MATERIALIZED (SELECT s, grp, node, r, row_number() OVER (PARTITION BY s, grp ORDER BY round(r, 12) DESC, node) AS rank, its, nn, coalesce(ne, 0) AS ne
          FROM {p}all a JOIN {p}its i USING (s, grp) JOIN (SELECT s, grp, node, nn FROM {p}n) USING (s, grp, node) LEFT JOIN {p}ne USING (s, grp) WHERE a.k = i.its)""",
    ]


CENTRAL = [
    "cn AS (SELECT s, -1 AS grp, CAST(node AS VARCHAR) AS node, x FROM scored)",
    "ce AS (SELECT s, -1 AS grp, CAST(a AS VARCHAR) AS src, CAST(b AS VARCHAR) AS dst, w FROM es)",
    *walk("cw", "cn", "ce"),
]


def decentral(scope: str = "subgraph") -> list[str]:
    """Walks of clusters after one exchange, then decision, combination and final(s, node, tier, score, rank)."""
    inside = "src IS NULL OR (SELECT c.cluster FROM cmap c WHERE c.device = src) = (SELECT c.cluster FROM cmap c WHERE c.device = parts.node)"
    local = "SELECT s, node, coalesce(sum(x), 0) AS x FROM seen LEFT JOIN (SELECT s, node, x FROM parts WHERE " + inside + ") USING (s, node) GROUP BY 1, 2" if scope == "subgraph" else "SELECT * FROM scored"
    return [
        f"ln AS MATERIALIZED (SELECT s, cluster AS grp, node, x FROM ({local}) JOIN cmap ON device = node)",
        "le AS MATERIALIZED (SELECT s, p.cluster AS c1, q.cluster AS c2, a, b, w FROM es JOIN cmap p ON p.device = a JOIN cmap q ON q.device = b)",
        "cross_ AS MATERIALIZED (SELECT * FROM le WHERE c1 <> c2)",
        "linked AS MATERIALIZED (SELECT s, c1 AS grp, c2 AS other FROM cross_ UNION SELECT s, c2, c1 FROM cross_)",
        "means AS MATERIALIZED (SELECT s, grp, sum(x) / any_value(n) AS mean FROM ln JOIN (SELECT cluster AS grp, count(*) AS n FROM cmap GROUP BY 1) USING (grp) GROUP BY 1, 2)",
        "dn AS (SELECT s, grp, CAST(node AS VARCHAR) AS node, x FROM ln UNION ALL SELECT l.s, l.grp, 'cluster:' || l.other, coalesce(mean, 0) FROM linked l LEFT JOIN means m ON m.s = l.s AND m.grp = l.other)",
        """de AS (SELECT s, c1 AS grp, CAST(a AS VARCHAR) AS src, CAST(b AS VARCHAR) AS dst, w FROM le WHERE c1 = c2 UNION ALL SELECT s, c1, CAST(a AS VARCHAR), 'cluster:' || c2, sum(w) FROM cross_ GROUP BY s, c1, a, c2
          UNION ALL SELECT s, c2, 'cluster:' || c1, CAST(b AS VARCHAR), sum(w) FROM cross_ GROUP BY s, c1, c2, b)""",
        *walk("dw", "dn", "de"),
        "who AS MATERIALIZED (SELECT DISTINCT s, grp FROM linked)",
        "first_ AS (SELECT s, grp, node, node LIKE 'cluster:%' AS points FROM dwrank SEMI JOIN who USING (s, grp) WHERE rank = 1)",
        "votes AS (SELECT s, count(*) FILTER (NOT points) AS locals, max(grp) FILTER (NOT points) AS w FROM first_ GROUP BY 1)",
        "decision AS MATERIALIZED (SELECT s, CASE WHEN agreed THEN 'consensus' WHEN locals > 1 THEN 'conflict' ELSE 'pointing' END AS mode, CASE WHEN agreed THEN w END AS winner FROM (SELECT s, locals, w, locals = 1 AND NOT EXISTS (SELECT 1 FROM first_ f WHERE f.s = votes.s AND points AND node <> 'cluster:' || w) AS agreed FROM votes))",
        "part AS MATERIALIZED (SELECT s, grp, node, r FROM dwrank WHERE node NOT LIKE 'cluster:%')",
        "given AS MATERIALIZED (SELECT s, grp, CAST(split_part(node, ':', 2) AS BIGINT) AS other, r FROM dwrank WHERE node LIKE 'cluster:%')",
        "influence AS MATERIALIZED (SELECT p.s, y.grp AS seen_by, p.node, y.r * p.r AS r FROM part p JOIN given y ON y.s = p.s AND y.other = p.grp)",
        "combined AS MATERIALIZED (SELECT s, node, sum(r) / any_value(n) AS score FROM (SELECT s, node, r FROM part SEMI JOIN who USING (s, grp) UNION ALL SELECT s, node, r FROM influence) JOIN (SELECT s, count(*) AS n FROM who GROUP BY 1) USING (s) GROUP BY 1, 2)",
        "mass AS (SELECT s, grp, CASE WHEN sum(t) OVER (PARTITION BY s) > 0 THEN t / sum(t) OVER (PARTITION BY s) ELSE 1 END AS share FROM (SELECT s, grp, sum(x) AS t FROM ln GROUP BY 1, 2))",
        "tiers AS (SELECT part.s, part.node, CASE WHEN coalesce(part.grp = winner, false) THEN 0 WHEN c.score IS NOT NULL THEN 1 ELSE 2 END AS tier, part.r * share AS alone, c.score FROM part JOIN mass USING (s, grp) LEFT JOIN combined c ON c.s = part.s AND c.node = part.node LEFT JOIN decision ON decision.s = part.s)",
        "final AS MATERIALIZED (SELECT s, node, tier, row_number() OVER (PARTITION BY s ORDER BY tier, round(CASE WHEN tier = 1 THEN score ELSE alone END, 12) DESC, node) AS rank FROM tiers)",
    ]


#: compared(s, grp, fault, root, type, rank_c, rank_d, t_c, t_d): both runs beside the truth.
COMPARED = [
    "cwork AS (SELECT s, max(its * (nn + ne))::DOUBLE AS t, sum(its * (nn + ne))::DOUBLE AS total FROM (SELECT DISTINCT s, grp, its, nn, ne FROM cwrank) GROUP BY 1)",
    "dwork AS (SELECT s, max(its * (nn + ne))::DOUBLE AS t, sum(its * (nn + ne))::DOUBLE AS total FROM (SELECT DISTINCT s, grp, its, nn, ne FROM dwrank) GROUP BY 1)",
    """compared AS MATERIALIZED (SELECT sc.s, sc.grp, fault, CASE WHEN EXISTS (SELECT 1 FROM who WHERE who.s = sc.s) THEN 'multi' ELSE 'single' END AS type,
      coalesce(c.rank, 1 + (SELECT count(*) FROM cwrank x WHERE x.s = sc.s)) AS rank_c, coalesce(f.rank, 1 + (SELECT count(*) FROM final x WHERE x.s = sc.s)) AS rank_d, cwork.t AS t_c, dwork.t AS t_d
      FROM sc LEFT JOIN cwrank c ON c.s = sc.s AND c.node = CAST(root AS VARCHAR) LEFT JOIN final f ON f.s = sc.s AND f.node = CAST(root AS VARCHAR) LEFT JOIN cwork ON cwork.s = sc.s LEFT JOIN dwork ON dwork.s = sc.s)""",
]
_REDUCED = "round(avg((t_c - t_d) / t_c * 100), 6) AS avg_reduction, round((sum(t_c) - sum(t_d)) / sum(t_c) * 100, 6) AS total_reduction"


def _measures(rank: str) -> str:
    return ", ".join(f"round(avg(({rank} <= {k})::INT), 6) AS acc_{k}" for k in (1, 2, 3, 5, 10)) + f", round(avg({rank}), 6) AS mar, round(avg(1.0::DOUBLE / {rank}), 6) AS mrr"


def _summary(by: str) -> str:
    return " UNION ALL ".join(f"SELECT {by}, count(*) AS scenarios, {_measures(r)}, {_REDUCED}, '{m}' AS method FROM compared GROUP BY {by}" for m, r in (("centralized", "rank_c"), ("decentralized", "rank_d")))


_BASE = [SPANS, THIN, *GENERATOR]
_SCORED = [*_BASE, *FLAGS, *SCORES]
_RUN = [SPANS, THIN, *clusters(), *GENERATOR, *FLAGS, *SCORES, *CENTRAL, *decentral(), *COMPARED]
_DECENTRAL = [SPANS, THIN, *clusters(), *GENERATOR, *FLAGS, *SCORES, *decentral()]
_LABEL = "['cpu', 'mem', 'io', 'net_in', 'net_out', 'errors']"
_LINKS = "p AS (SELECT s, least(c1, c2) AS lo, greatest(c1, c2) AS hi, min(c1) AS f, sum(w) AS w FROM cross_ GROUP BY 1, 2, 3), q AS (SELECT s, f, CASE WHEN f = lo THEN hi ELSE lo END AS o, w FROM p)"
_MESSAGES = f"""{_LINKS}, sent AS (SELECT s, f AS src, o AS dst, 'wait' AS kind, NULL::DOUBLE AS mean_s, NULL::DOUBLE AS crossing_w FROM q
  UNION ALL SELECT q.s, f, o, 'score', coalesce(mean, 0), w FROM q LEFT JOIN means m ON m.s = q.s AND m.grp = f UNION ALL SELECT q.s, o, f, 'score', coalesce(mean, 0), NULL FROM q LEFT JOIN means m ON m.s = q.s AND m.grp = o)"""

ORACLES = {
    "loc_series": statement(_BASE, f"SELECT {_LABEL}[j + 1] AS metric, count(*) AS n, round(avg(v), 6) AS last FROM series WHERE e < 100 AND t = 39 GROUP BY 1"),
    "loc_flags": statement([*_BASE, *FLAGS], f"SELECT s AS scenario, CASE WHEN e < 100 THEN CAST(e AS VARCHAR) ELSE g.a || '>' || g.b END AS entity, CASE WHEN e < 100 THEN {_LABEL}[j + 1] ELSE ['p50', 'p90', 'p99'][j + 1] END AS metric FROM flagged LEFT JOIN g ON e = 100 + id"),
    "score_node": statement(_SCORED, "SELECT s AS scenario, CAST(node AS VARCHAR) AS node, round(x, 6) AS s FROM scored"),
    "score_edge": statement(_SCORED, "SELECT s AS scenario, CAST(a AS VARCHAR) AS src, CAST(b AS VARCHAR) AS dst, round(w, 6) AS w FROM es"),
    "score_node_local": statement([SPANS, THIN, *clusters(), *GENERATOR, *FLAGS, *SCORES, *decentral()[:1]], "SELECT s AS scenario, CAST(grp AS BIGINT) AS grp, CAST(node AS VARCHAR) AS node, round(x, 6) AS s FROM ln"),
    "loc_central": statement([*_SCORED, *CENTRAL], "SELECT s AS scenario, node, CAST(rank AS INT) AS rank FROM cwrank"),
    "loc_decentral": statement(_DECENTRAL, "SELECT s AS scenario, node, CAST(rank AS INT) AS rank FROM final"),
    "loc_messages": statement([*_DECENTRAL, _MESSAGES], "SELECT s AS scenario, src AS from_cluster, dst AS to_cluster, kind, round(mean_s, 6) AS mean_s, round(crossing_w, 6) AS crossing_w FROM sent"),
    "loc_combined": statement(_DECENTRAL, "SELECT s AS scenario, node, round(score, 6) AS score FROM combined"),
    "loc_decisions": statement(_DECENTRAL, "SELECT s AS scenario, mode, CAST(winner AS BIGINT) AS winner FROM decision"),
    "op_influence": statement(_DECENTRAL, "SELECT s AS scenario, CAST(seen_by AS BIGINT) AS seen_by, node, round(r, 6) AS r FROM influence"),
    "eval_accuracy": statement(_RUN, _summary("grp")),
    "eval_breakdown": statement(_RUN, _summary("type, grp")),
    "eval_by_fault": statement(_RUN, _summary("fault")),
    "eval_time_cost": statement(_RUN, f"SELECT grp, count(*) AS scenarios, round(avg(t_c), 6) AS central_visits, round(avg(t_d), 6) AS slowest_visits, {_REDUCED} FROM compared GROUP BY 1"),
    "eval_conflicts": statement(_DECENTRAL, "SELECT round(avg((mode <> 'consensus')::INT), 6) AS conflict_rate, count(*) AS multi FROM decision"),
    "eval_communication": statement([*_DECENTRAL, _MESSAGES], "SELECT count(*) AS messages, CAST(sum(((mean_s IS NOT NULL)::INT + (crossing_w IS NOT NULL)::INT) * 8) AS BIGINT) AS exchanged_bytes, (SELECT count(*) * 8 FROM series) AS central_bytes FROM sent"),
    "eval_idle": statement(_DECENTRAL, "SELECT l.s AS scenario, l.grp AS c1, l.other AS c2, 0.0::DOUBLE AS wait_sent, 0.0::DOUBLE AS wait_received, greatest(a.t, b.t) AS ready, abs(a.t - b.t) AS idle FROM linked l JOIN (SELECT DISTINCT s, grp, (nn + ne)::DOUBLE AS t FROM dwrank) a ON a.s = l.s AND a.grp = l.grp JOIN (SELECT DISTINCT s, grp, (nn + ne)::DOUBLE AS t FROM dwrank) b ON b.s = l.s AND b.grp = l.other WHERE l.grp < l.other"),
    "op_rollup_breakdown": statement(_RUN, "SELECT type, grp, count(*) AS n, round(avg(rank_d), 6) AS mar, CAST(grouping(type, grp) AS BIGINT) AS level FROM compared GROUP BY ROLLUP (type, grp)"),
    "op_variant_diff": statement([*_DECENTRAL, *CENTRAL], "SELECT s AS scenario, node FROM cwrank WHERE rank = 1 EXCEPT SELECT s, node FROM final WHERE rank = 1"),
}


# ---- clusters and subgraphs of the nation calls, thinned or whole

_MAP = [SPANS, THIN, *clusters()]
_WINDOWED = [SPANS, "thin AS MATERIALIZED (SELECT trace % 7 AS g, a AS src, b AS dst, count(*) AS freq FROM ncalls WHERE a % 3 = b % 3 OR trace % 128 = 0 GROUP BY 1, 2, 3)", *clusters(key="g"), "per_ AS (SELECT s, count(DISTINCT cluster) AS clusters FROM (SELECT unnest(range(0, 383)) AS s) JOIN cmap ON k = s % 7 GROUP BY 1)"]
_TAUS = "[0.001, 0.005, 0.0075, 0.01, 0.02, 0.03, 0.05, 0.1]"
_SWEPT = [SPANS, THIN, "swept AS MATERIALIZED (SELECT src, dst, freq, unnest(range(0, 8)) AS g FROM thin)", *clusters(tau=f"{_TAUS}[k + 1]::DOUBLE", calls="swept", key="g")]
_SWEPT[_SWEPT.index(next(x for x in _SWEPT if x.startswith("tau ")))] = f"tau AS MATERIALIZED (SELECT k, any_value({_TAUS}[k + 1])::DOUBLE * sum(w) AS tau FROM w0 GROUP BY 1)"
_ENDS = "ends AS MATERIALIZED (SELECT src, dst, freq, p.cluster AS c1, q.cluster AS c2 FROM thin JOIN cmap p ON p.device = src JOIN cmap q ON q.device = dst)"
_RECEIVED = "got AS MATERIALIZED (SELECT c2 AS grp, dst AS node, sum(freq)::DOUBLE AS s FROM ends GROUP BY 1, 2), mean AS MATERIALIZED (SELECT grp, sum(s) / any_value(n) AS s FROM got JOIN (SELECT cluster AS grp, count(*) AS n FROM cmap GROUP BY 1) USING (grp) GROUP BY 1)"
_LINK = "x AS (SELECT DISTINCT c1 AS a, c2 AS b FROM ends WHERE c1 <> c2), l AS MATERIALIZED (SELECT a, b FROM x UNION SELECT b, a FROM x)"
_CUT = "SELECT c1 AS cluster, sum(CASE WHEN c1 = c2 THEN freq ELSE 0 END)::BIGINT AS intra, sum(CASE WHEN c1 = c2 THEN 0 ELSE freq END)::BIGINT AS inter FROM ends GROUP BY 1"
_SUB = [*_MAP, _ENDS]

ORACLES |= {
    "clu_map": statement(_MAP, "SELECT device, cluster FROM cmap"),
    "clu_map_greedy": statement(_MAP, "SELECT device, cluster FROM cmap"),
    "clu_map_full": statement([SPANS, FULL, *clusters()], "SELECT device, cluster FROM cmap"),
    "clu_weights": statement([SPANS, THIN], "SELECT least(src, dst) AS c1, greatest(src, dst) AS c2, sum(freq)::BIGINT AS w FROM thin GROUP BY 1, 2"),
    "clu_cut_ratio": statement([*_SUB, f"cut AS ({_CUT})"], "SELECT *, round(intra / (intra + inter), 6) AS ratio FROM cut"),
    "clu_quality": statement([*_SUB, f"cut AS ({_CUT})"], "SELECT cluster, n AS devices, n AS services, intra, inter, round(intra / (intra + inter), 6) AS ratio FROM (SELECT cluster, count(*) AS n FROM cmap GROUP BY 1) LEFT JOIN cut USING (cluster)"),
    "clu_per_scenario": statement(_WINDOWED, "SELECT CAST(s AS INT) AS scenario, clusters FROM per_"),
    "clu_count": statement(_WINDOWED, "SELECT clusters, count(*) AS scenarios FROM per_ GROUP BY 1"),
    "clu_tau_sweep": statement(_SWEPT, f"SELECT CAST(k AS INT) AS sweep, {_TAUS}[k + 1]::DOUBLE AS tau, count(DISTINCT cluster) AS clusters FROM cmap GROUP BY k"),
    "sub_nodes": statement(_SUB, """SELECT cluster, CAST(device AS VARCHAR) AS node, false AS is_shadow, NULL::VARCHAR AS remote_service, NULL::BIGINT AS remote_cluster FROM cmap
      UNION ALL SELECT DISTINCT c1, 'shadow:' || dst, true, CAST(dst AS VARCHAR), c2 FROM ends WHERE c1 <> c2"""),
    "sub_edges": statement(_SUB, "SELECT c1 AS cluster, CAST(src AS VARCHAR) AS src, CASE WHEN c1 <> c2 THEN 'shadow:' || dst ELSE CAST(dst AS VARCHAR) END AS dst, freq, c1 <> c2 AS crosses FROM ends"),
    "sub_shadow": statement(_SUB, "SELECT c1 AS cluster, count(DISTINCT dst) AS shadows FROM ends WHERE c1 <> c2 GROUP BY 1"),
    "op_two_way_crossings": statement([*_SUB, _LINK], "SELECT x.a AS c1, x.b AS c2 FROM x JOIN x y ON x.a = y.b AND x.b = y.a WHERE x.a < x.b"),
    "op_crossings": statement(_SUB, "SELECT c1 AS cluster, CAST(src AS VARCHAR) AS src, CAST(dst AS VARCHAR) AS callee, c2 AS callee_cluster, freq::DOUBLE AS w FROM ends WHERE c1 <> c2"),
    "op_mean_score": statement([*_SUB, _RECEIVED], "SELECT grp AS cluster, round(s, 6) AS mean_s FROM mean"),
    "op_augment": statement([*_SUB, _RECEIVED, _LINK], "SELECT grp, CAST(node AS VARCHAR) AS node, round(s, 6) AS s FROM got UNION ALL SELECT a, 'cluster:' || b, round(coalesce(s, 0), 6) FROM l LEFT JOIN mean ON mean.grp = l.b"),
    "op_messages": statement([*_SUB, _RECEIVED, "xw AS (SELECT c1, c2, sum(freq)::DOUBLE AS w FROM ends WHERE c1 <> c2 GROUP BY 1, 2), p AS (SELECT least(c1, c2) AS lo, greatest(c1, c2) AS hi, min(c1) AS f, sum(w) AS w FROM xw GROUP BY 1, 2), q AS (SELECT f, CASE WHEN f = lo THEN hi ELSE lo END AS o, w FROM p)"],
      "SELECT f AS from_cluster, o AS to_cluster, 'wait' AS kind, NULL::DOUBLE AS mean_s, NULL::DOUBLE AS crossing_w FROM q UNION ALL SELECT f, o, 'score', round(coalesce(s, 0), 6), w FROM q LEFT JOIN mean ON grp = f UNION ALL SELECT o, f, 'score', round(coalesce(s, 0), 6), NULL FROM q LEFT JOIN mean ON grp = o"),
    "op_combine": statement([*_SUB, _RECEIVED, _LINK, """met AS MATERIALIZED (SELECT l.a, l.b, coalesce(s, 0) AS s FROM l LEFT JOIN mean ON grp = l.b), tot AS (SELECT grp, sum(s) AS t FROM (SELECT grp, s FROM got UNION ALL SELECT a, s FROM met) GROUP BY 1),
      r AS MATERIALIZED (SELECT grp, node, s / t AS r FROM got JOIN tot USING (grp) WHERE grp IN (SELECT a FROM l)), gave AS (SELECT b, s / t AS mass FROM met JOIN tot ON grp = a)"""],
      "SELECT CAST(node AS VARCHAR) AS node, round(sum(r) / (SELECT count(DISTINCT a) FROM l), 6) AS score FROM (SELECT node, r FROM r UNION ALL SELECT node, mass * r FROM r JOIN gave ON b = grp) GROUP BY 1"),
    "eval_scaling": statement([SPANS, """sup AS (SELECT * FROM (SELECT service AS src, lead(service) OVER w AS dst FROM spans WINDOW w AS (PARTITION BY trace ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice)) WHERE src <> dst),
      sizes AS (SELECT n FROM (SELECT unnest([10, 25, 50, 100, 250, 500, 1000]) AS n) WHERE n <= greatest(10, (SELECT count(*) FROM supplier))),
      fe AS MATERIALIZED (SELECT n AS s, src % n AS a, dst % n AS b, count(*)::DOUBLE AS w FROM sup, sizes WHERE src % n <> dst % n GROUP BY 1, 2, 3),
      fn AS MATERIALIZED (SELECT s, b AS node, sum(w) AS x FROM fe GROUP BY 1, 2),
      cn AS (SELECT s, -1 AS grp, CAST(node AS VARCHAR) AS node, x FROM fn), ce AS (SELECT s, -1 AS grp, CAST(a AS VARCHAR) AS src, CAST(b AS VARCHAR) AS dst, w FROM fe),
      dn AS (SELECT s, node % 4 AS grp, CAST(node AS VARCHAR) AS node, x FROM fn), de AS (SELECT s, a % 4 AS grp, CAST(a AS VARCHAR) AS src, CAST(b AS VARCHAR) AS dst, w FROM fe WHERE a % 4 = b % 4)""",
      *walk("cw", "cn", "ce"), *walk("dw", "dn", "de")], """SELECT CAST(s AS INT) AS services, edges, c AS central_visits, d AS slowest_visits FROM (SELECT s, count(*) AS edges FROM fe GROUP BY 1)
      JOIN (SELECT s, max(its * (nn + ne))::DOUBLE AS c FROM cwrank GROUP BY 1) USING (s) JOIN (SELECT s, max(its * (nn + ne))::DOUBLE AS d FROM dwrank GROUP BY 1) USING (s)"""),
    "loc_triggers": statement([*_BASE, *FLAGS], "SELECT s AS scenario, CASE WHEN bool_or(e < 100) THEN CASE WHEN bool_or(e >= 100) THEN 'device,network,service' ELSE 'device,service' END ELSE 'network' END AS layers, count(*) + count(*) FILTER (e < 100) AS n_flags FROM flagged GROUP BY 1"),
    "score_explain": statement([*_SCORED, f"""term AS (SELECT s, e AS node, least({_LABEL}[j1 + 1], {_LABEL}[j2 + 1]) AS a, greatest({_LABEL}[j1 + 1], {_LABEL}[j2 + 1]) AS b, r FROM pairs WHERE e < 100 UNION ALL SELECT s, b, 'call', CAST(a AS VARCHAR), x FROM best)"""],
      "SELECT s AS scenario, CAST(node AS VARCHAR) AS node, a, b, round(r, 6) AS corr FROM term QUALIFY row_number() OVER (PARTITION BY s, node ORDER BY round(r, 12) DESC, a, b) <= 3"),
    "score_rt_baseline": statement([*_SCORED, """rtk AS MATERIALIZED (SELECT fs.s, fs.e FROM fs JOIN g ON fs.e = 100 + g.id WHERE j = 1 AND t = 39 QUALIFY row_number() OVER (PARTITION BY fs.s ORDER BY v DESC, CAST(a AS VARCHAR) DESC, CAST(b AS VARCHAR) DESC) = 1),
      rt AS MATERIALIZED (SELECT fs.s, t, v FROM fs SEMI JOIN rtk ON rtk.s = fs.s AND rtk.e = fs.e WHERE j = 1),
      rts AS (SELECT s, e AS node, max(r) AS x FROM (SELECT fs.s, fs.e, fs.j, abs(corr(fs.v, rt.v)) AS r FROM fs JOIN rt USING (s, t) WHERE fs.e < 100 GROUP BY ALL) GROUP BY 1, 2)"""],
      "SELECT s AS scenario, CAST(node AS VARCHAR) AS node, round(coalesce(x, 0), 6) AS s FROM seen LEFT JOIN rts USING (s, node)"),
}
