"""DuckDB SQL for the workloads that SQL can express, by query name."""

from __future__ import annotations

from edgeloc.plans import scenario_sql

_SPANS = """spans AS (SELECT l_orderkey AS trace, l_suppkey AS service, CAST(s_nationkey AS BIGINT) AS device, abs(date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))) AS latency, CAST(o_orderdate AS DATE) AS day,
  l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN supplier ON s_suppkey = l_suppkey),
calls AS (SELECT * FROM (SELECT trace, service AS src, device AS a, lead(service) OVER w AS dst, lead(device) OVER w AS b, lead(latency) OVER w AS latency, lead(day) OVER w AS day FROM spans
  WINDOW w AS (PARTITION BY trace ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice)) WHERE src <> dst)"""
_EVENTS = """ev AS (SELECT *, CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 20) AS BIGINT) AS device, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS t FROM events),
es AS (SELECT *, event_type || '_' || device AS service FROM ev),
ecalls AS (SELECT * FROM (SELECT user_id AS trace, service AS src, lead(service) OVER w AS dst, lead(value) OVER w AS latency, lead(t) OVER w AS t FROM es WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE src <> dst)"""
_NATION = "SELECT a AS src, b AS dst, count(*) AS freq FROM calls WHERE a <> b GROUP BY 1, 2"
_ALIGNED = """aligned AS (SELECT entity, t, coalesce(n, 0)::DOUBLE AS value FROM (SELECT DISTINCT service AS entity FROM es) CROSS JOIN (SELECT unnest(range(0, 30)) AS t) LEFT JOIN (SELECT service AS entity, t, count(*) AS n FROM es GROUP BY 1, 2) USING (entity, t)),
unit AS (SELECT entity, t, value, value / sqrt(sum(value * value) OVER (PARTITION BY entity)) AS z FROM aligned)"""
_PCT = "SELECT src, dst, t, metric, round(value, 6) AS value FROM (SELECT src, dst, {t} AS t, quantile_cont(latency, 0.5)::DOUBLE AS p50, quantile_cont(latency, 0.9)::DOUBLE AS p90, quantile_cont(latency, 0.99)::DOUBLE AS p99 FROM {of} GROUP BY 1, 2, 3) UNPIVOT (value FOR metric IN (p50, p90, p99))"


def _steps(k: int) -> str:
    """k steps of the walk over nation calls, personalized by calls received."""
    out = [
        f"f AS ({_NATION})", "tot AS (SELECT src, sum(freq) AS t FROM f GROUP BY 1)", "p AS (SELECT f.src, dst, freq::DOUBLE / t AS p FROM f JOIN tot USING (src))",
        "s AS (SELECT dst AS node, sum(freq)::DOUBLE / (SELECT sum(freq) FROM f) AS s FROM f GROUP BY 1)", "r0 AS (SELECT node, s AS r FROM s)",
    ]
    for n in range(1, k + 1):
        out.append(f"r{n} AS (SELECT s.node, 0.5 * (coalesce(m, 0) + (SELECT coalesce(sum(r), 0) FROM r{n - 1} WHERE node NOT IN (SELECT src FROM tot)) * s.s) + 0.5 * s.s AS r FROM s LEFT JOIN (SELECT dst AS node, sum(r * p) AS m FROM r{n - 1} JOIN p ON p.src = node GROUP BY 1) USING (node))")
    return ", ".join(out)


_NATIONS = "n AS (SELECT n_regionkey AS scenario, n_nationkey AS node, coalesce((SELECT sum(freq) FROM f WHERE dst = n_nationkey), 0)::DOUBLE AS r, coalesce((SELECT sum(freq) FROM f WHERE src = n_nationkey), 0)::DOUBLE AS t FROM nation)"


def _active(days: int) -> str:
    """Metrics of services by bins of days, those flagged whose range is above two thirds of their largest value."""
    return f"""sm AS (SELECT * FROM (SELECT service AS node, CAST(floor(t / {days}) AS INT) AS t, count(*)::DOUBLE AS count, avg(value) AS avg, max(value) AS max, quantile_cont(value, 0.5) AS p50, quantile_cont(value, 0.9) AS p90, quantile_cont(value, 0.99) AS p99 FROM es GROUP BY 1, 2) UNPIVOT (value FOR metric IN (count, avg, max, p50, p90, p99))),
      sa AS (SELECT node, metric, t, coalesce(value, 0) AS value FROM (SELECT DISTINCT node, metric FROM sm) CROSS JOIN (SELECT unnest(range(0, {30 // days})) AS t) LEFT JOIN sm USING (node, metric, t)),
      hot AS (SELECT * FROM sa WINDOW w AS (PARTITION BY node, metric) QUALIFY (max(value) OVER w - min(value) OVER w) * 3 > max(value) OVER w * 2)"""


def _fold(rows: str, keys: str, beta: str) -> str:
    """Features of series rows(keys, i, z), taken in order of i from 1: the nearest feature takes a value if its radius stays up to beta, else a new one opens."""
    k = [x.strip() for x in keys.split(",")]
    same = " AND ".join(f"f.{x} = r.{x}" for x in k)
    mine = ", ".join(f"f.{x}" for x in k)
    return f"""fold AS (SELECT {keys}, i, [1.0::DOUBLE] AS n, [z] AS ls, [z * z] AS ss FROM {rows} WHERE i = 1 UNION ALL
      SELECT {keys}, i, CASE WHEN fits THEN list_transform(n, lambda x, p: CASE WHEN p = near THEN x + 1 ELSE x END) ELSE list_append(n, 1.0::DOUBLE) END,
        CASE WHEN fits THEN list_transform(ls, lambda x, p: CASE WHEN p = near THEN x + z ELSE x END) ELSE list_append(ls, z) END, CASE WHEN fits THEN list_transform(ss, lambda x, p: CASE WHEN p = near THEN x + z * z ELSE x END) ELSE list_append(ss, z * z) END
      FROM (SELECT *, sqrt(greatest(0.0, (ss[near] + z * z) / (n[near] + 1) - ((ls[near] + z) / (n[near] + 1)) * ((ls[near] + z) / (n[near] + 1)))) <= {beta} AS fits
        FROM (SELECT {mine}, r.i, r.z, n, ls, ss, list_position(list_transform(n, lambda x, p: abs(ls[p] / x - r.z)), list_min(list_transform(n, lambda x, p: abs(ls[p] / x - r.z)))) AS near FROM fold f JOIN {rows} r ON {same} AND r.i = f.i + 1)))"""


ORACLES = {
    "wl_calls_supplier": f"WITH {_SPANS} SELECT trace, src, dst FROM calls",
    "wl_freq_supplier": f"WITH {_SPANS} SELECT src, dst, count(*) AS freq FROM calls GROUP BY 1, 2",
    "wl_freq_nation": f"WITH {_SPANS} {_NATION}",
    "wl_calls_events": f"WITH {_EVENTS} SELECT trace, src, dst, latency FROM ecalls",
    "wl_freq_events": f"WITH {_EVENTS} SELECT src, dst, count(*) AS freq FROM ecalls GROUP BY 1, 2",
    "op_unlinked_services": f"WITH {_SPANS}, f AS (SELECT src, dst FROM calls GROUP BY 1, 2 HAVING count(*) > 1) SELECT s_suppkey AS service FROM supplier WHERE s_suppkey NOT IN (SELECT src FROM f) AND s_suppkey NOT IN (SELECT dst FROM f)",
    "op_host_device": "SELECT device % 3 AS cluster, arg_max(device, capacity) AS host FROM (SELECT CAST(s_nationkey AS BIGINT) AS device, sum(s_acctbal) AS capacity FROM supplier GROUP BY 1) GROUP BY 1",
    "conv_calls": "SELECT src, dst, count(*) AS freq FROM (SELECT role AS src, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations) WHERE src <> dst GROUP BY 1, 2",
    "web_links": """SELECT src, CASE WHEN host = '' THEN src ELSE host END AS dst, count(*) AS freq FROM (SELECT src, regexp_extract(href, '://([^/?#]*)', 1) AS host FROM (SELECT regexp_extract(url, '://([^/?#]*)', 1) AS src, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)) GROUP BY 1, 2""",
    "op_session_traces": "SELECT user_id, session, count(*) AS n FROM (SELECT user_id, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL 3 DAY THEN 1 ELSE 0 END AS cut FROM events)) GROUP BY 1, 2",
    "wl_series_events": f"WITH {_EVENTS} SELECT entity, metric, t, round(value, 6) AS value FROM (SELECT service AS entity, t, count(*)::DOUBLE AS count, avg(value) AS avg, max(value) AS max, quantile_cont(value, 0.5) AS p50, quantile_cont(value, 0.9) AS p90, quantile_cont(value, 0.99) AS p99 FROM es GROUP BY 1, 2) UNPIVOT (value FOR metric IN (count, avg, max, p50, p90, p99))",
    "wl_series_supplier": "SELECT CAST(s_nationkey AS BIGINT) AS entity, CAST(year(l_shipdate) * 4 + quarter(l_shipdate) AS INT) AS t, count(*) AS n, round(sum(l_quantity), 6) AS qty, CAST(sum(CAST(round(l_discount * 100) AS BIGINT)) AS BIGINT) AS disc, CAST(sum(CAST(round(l_tax * 100) AS BIGINT)) AS BIGINT) AS tax FROM lineitem JOIN supplier ON s_suppkey = l_suppkey GROUP BY 1, 2",
    "wl_edge_latency": f"WITH {_SPANS}, n AS (SELECT a AS src, b AS dst, latency, day FROM calls WHERE a <> b) " + _PCT.format(t="CAST(year(day) * 2 + floor((month(day) - 1) / 6) AS BIGINT)", of="n"),
    "op_edge_percentiles": f"WITH {_EVENTS} " + _PCT.format(t="CAST(floor(t / 10) AS BIGINT)", of="ecalls"),
    "op_device_series": f"WITH {_EVENTS} SELECT entity, metric, t, round(value, 6) AS value FROM (SELECT device AS entity, t, count(*)::DOUBLE AS count, avg(value) AS avg, max(value) AS max, quantile_cont(value, 0.5) AS p50, quantile_cont(value, 0.9) AS p90, quantile_cont(value, 0.99) AS p99 FROM es GROUP BY 1, 2) UNPIVOT (value FOR metric IN (count, avg, max, p50, p90, p99))",
    "op_link_series": f"WITH {_EVENTS}, links AS (SELECT CAST(split_part(src, '_', -1) AS BIGINT) AS src, CAST(split_part(dst, '_', -1) AS BIGINT) AS dst, latency, t FROM ecalls WHERE split_part(src, '_', -1) <> split_part(dst, '_', -1)) " + _PCT.format(t="CAST(floor(t / 10) AS BIGINT)", of="links"),
    "op_series_align": f"WITH {_EVENTS}, {_ALIGNED} SELECT entity, 'count' AS metric, CAST(t AS INT) AS t, value FROM aligned",
    "op_l2_normalize": f"WITH {_EVENTS}, {_ALIGNED} SELECT entity, CAST(t AS INT) AS t, round(z, 6) AS value FROM unit",
    "op_sliding_rate": "SELECT CAST(date_diff('day', DATE '2024-01-01', CAST(d AS DATE)) AS INT) AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY 1, 2",
    "op_asof_metric": "SELECT event_id, last_value FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS last_value FROM events) WHERE event_type = 'click'",
    "op_interval_join": "SELECT i.event_id AS incident, count(*) AS n FROM events i JOIN events e ON e.user_id = i.user_id AND e.ts <= i.ts AND e.ts >= i.ts - INTERVAL 1 HOUR WHERE i.value > 200 GROUP BY 1",
    "op_props_json": f"WITH {_EVENTS} SELECT device, count(*) AS n FROM es GROUP BY 1",
    "det_gap_events": f"WITH {_EVENTS}, {_ALIGNED} SELECT entity, CAST(1 + sum(CASE WHEN z - p > 0.03 THEN 1 ELSE 0 END) AS INT) AS n_groups FROM (SELECT entity, z, lag(z) OVER (PARTITION BY entity ORDER BY z) AS p FROM unit) GROUP BY 1",
    "op_abs_corr_pairs": f"WITH {_EVENTS}, {_ALIGNED} SELECT a.entity AS e1, b.entity AS e2, round(abs(corr(a.value, b.value)), 6) AS corr FROM aligned a JOIN aligned b ON a.t = b.t AND a.entity < b.entity AND split_part(a.entity, '_', -1) = split_part(b.entity, '_', -1) GROUP BY 1, 2",
    "op_spearman": f"WITH {_EVENTS}, {_ALIGNED}, rk AS (SELECT entity, t, rank() OVER (PARTITION BY entity ORDER BY value) + (count(*) OVER (PARTITION BY entity, value) - 1) / 2.0 AS k FROM aligned) SELECT split_part(a.entity, '_', 1) AS kind, round(abs(corr(a.k, b.k)), 6) AS corr FROM rk a JOIN rk b ON a.t = b.t AND split_part(a.entity, '_', 1) = split_part(b.entity, '_', 1) WHERE a.entity LIKE '%\\_0' ESCAPE '\\' AND b.entity LIKE '%\\_1' ESCAPE '\\' GROUP BY 1",
    "op_spearman_pairs": f"WITH {_EVENTS}, {_ALIGNED}, rk AS (SELECT entity, t, rank() OVER (PARTITION BY entity ORDER BY value) + (count(*) OVER (PARTITION BY entity, value) - 1) / 2.0 AS k FROM aligned) SELECT a.entity AS e1, b.entity AS e2, round(abs(corr(a.k, b.k)), 6) AS corr FROM rk a JOIN rk b ON a.t = b.t AND a.entity < b.entity AND split_part(a.entity, '_', 1) = split_part(b.entity, '_', 1) GROUP BY 1, 2",
    "op_personalization": f"WITH {_SPANS}, f AS ({_NATION}), s AS (SELECT dst AS node, sum(freq) AS s FROM f GROUP BY 1) SELECT node % 3 AS grp, node, round(s::DOUBLE / sum(s) OVER (PARTITION BY node % 3), 6) AS p FROM s",
    "op_transition": f"WITH {_SPANS}, f AS ({_NATION}) SELECT src, dst, round(freq::DOUBLE / sum(freq) OVER (PARTITION BY src), 6) AS p FROM f",
    "op_ppr_k10": f"WITH {_SPANS}, {_steps(10)} SELECT node, round(r, 8) AS r FROM r10",
    "op_topk_causes": f"WITH {_SPANS}, {_steps(10)} SELECT node, round(r, 8) AS r, CAST(row_number() OVER (ORDER BY round(r, 8) DESC, node) AS INT) AS rank FROM r10 QUALIFY rank <= 5",
    "clu_initial": "SELECT CAST(n_nationkey AS BIGINT) AS device, CAST(n_nationkey AS BIGINT) AS cluster FROM nation",
    "clu_weights_full": f"WITH {_SPANS}, f AS ({_NATION}) SELECT least(src, dst) AS c1, greatest(src, dst) AS c2, sum(freq)::BIGINT AS w FROM f GROUP BY 1, 2",
    "op_cube_fault": "WITH t AS (SELECT CASE WHEN i < 146 THEN 'HH' ELSE 'SH' END AS grp, ['cpu', 'memory', 'latency', 'loss', 'duplication', 'corruption', 'disorder', 'delay', 'jitter'][i % 9 + 1] AS fault FROM range(0, 383) x(i)) SELECT grp, fault, count(*) AS n FROM t GROUP BY CUBE (grp, fault)",
    "stream_series": "SELECT CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INT) AS day, event_type, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1, 2",
    "op_span_lead": "SELECT event_id, epoch_us(lead(ts) OVER w) - epoch_us(ts) AS gap_us FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "op_href_links": """SELECT page_id, count(*) AS n_links, count(DISTINCT href) AS n_targets FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages) GROUP BY 1""",
    "op_acc_mar_mrr": f"""WITH {_SPANS}, f AS ({_NATION}), {_NATIONS}, k AS (SELECT *, row_number() OVER (PARTITION BY scenario ORDER BY r DESC, node) AS rank FROM n),
      c AS (SELECT n_regionkey AS scenario, c_nationkey AS root FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY 1, 2 QUALIFY row_number() OVER (PARTITION BY n_regionkey ORDER BY count(*) DESC, c_nationkey DESC) = 1)
      SELECT count(*) AS scenarios, {", ".join(f"round(avg((rank <= {k})::INT), 6) AS acc_{k}" for k in (1, 2, 3, 5, 10))}, round(avg(rank), 6) AS mar, round(avg(1.0::DOUBLE / rank), 6) AS mrr FROM k JOIN c ON k.scenario = c.scenario AND node = root""",
    "op_time_reduction": f"WITH {_SPANS}, f AS ({_NATION}), {_NATIONS}, g AS (SELECT scenario, sum(t) AS c, max(t) AS d FROM n GROUP BY 1) SELECT round(avg((c - d) / c * 100), 6) AS avg_reduction, round((sum(c) - sum(d)) / sum(c) * 100, 6) AS total_reduction FROM g",
    "score_metric": f"WITH {_EVENTS}, {_active(1)} SELECT node, round(sum(CASE WHEN m1 < m2 THEN r ELSE 0 END), 6) AS s_metric FROM (SELECT a.node, a.metric AS m1, b.metric AS m2, CASE WHEN stddev_pop(a.value) > 0 AND stddev_pop(b.value) > 0 THEN abs(corr(a.value, b.value)) ELSE 0 END AS r FROM hot a JOIN hot b ON a.node = b.node AND a.t = b.t AND a.metric <= b.metric GROUP BY 1, 2, 3) GROUP BY 1",
    "score_edge_influence": f"""WITH {_EVENTS}, {_active(3)}, e AS (SELECT src, dst, CAST(floor(t / 3) AS INT) AS t, quantile_cont(latency, 0.9)::DOUBLE AS value FROM ecalls GROUP BY 1, 2, 3),
      ea AS (SELECT src, dst, t, coalesce(value, 0) AS value FROM (SELECT DISTINCT src, dst FROM e) CROSS JOIN (SELECT unnest(range(0, 10)) AS t) LEFT JOIN e USING (src, dst, t)), eh AS (SELECT * FROM ea QUALIFY min(value) OVER (PARTITION BY src, dst) = 0)
      SELECT node, round(sum(best), 6) AS s_edge FROM (SELECT src, node, max(r) AS best FROM (SELECT eh.src, hot.node, hot.metric, CASE WHEN stddev_pop(eh.value) > 0 AND stddev_pop(hot.value) > 0 THEN abs(corr(eh.value, hot.value)) ELSE 0 END AS r FROM eh JOIN hot ON hot.node = eh.dst AND hot.t = eh.t GROUP BY 1, 2, 3) GROUP BY 1, 2) GROUP BY 1""",
}

_ROWS = "zs AS MATERIALIZED (SELECT entity, t + 1 AS i, z FROM unit)"
_BETAS = "bs AS MATERIALIZED (SELECT beta, entity, t + 1 AS i, z FROM unit, (SELECT unnest([0.01, 0.02, 0.03, 0.05, 0.07, 0.1])::DOUBLE AS beta))"
_SEEN = "vs AS MATERIALIZED (SELECT event_type AS entity, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) AS i, value / 1000 AS z FROM events)"
_LAST = "last_ AS (SELECT * FROM fold QUALIFY row_number() OVER (PARTITION BY {0} ORDER BY i DESC) = 1)"
_WEB = """host AS MATERIALIZED (SELECT src, CASE WHEN host = '' THEN src ELSE host END AS dst, count(*)::DOUBLE AS w FROM (SELECT src, regexp_extract(href, '://([^/?#]*)', 1) AS host FROM (SELECT regexp_extract(url, '://([^/?#]*)', 1) AS src, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)) GROUP BY 1, 2),
wn AS (SELECT 0 AS s, 0 AS grp, node, sum(w) AS x FROM (SELECT src AS node, w FROM host UNION ALL SELECT dst, w FROM host) GROUP BY 3), we AS (SELECT 0 AS s, 0 AS grp, src, dst, w FROM host)"""

ORACLES |= scenario_sql.ORACLES | {
    "det_birch_events": f"WITH RECURSIVE {_EVENTS}, {_ALIGNED}, {_ROWS}, {_fold('zs', 'entity', '0.07')}, {_LAST.format('entity')} SELECT entity, 'count' AS metric, CAST(len(n) AS INT) AS n_features, len(n) > 1 AS is_anomalous FROM last_",
    "det_birch_sweep": f"WITH RECURSIVE {_EVENTS}, {_ALIGNED}, {_BETAS}, {_fold('bs', 'beta, entity', 'beta')}, {_LAST.format('beta, entity')} SELECT beta, CAST(sum((len(n) > 1)::INT) AS BIGINT) AS flagged FROM last_ GROUP BY 1",
    "stream_detect": f"WITH RECURSIVE {_SEEN}, {_fold('vs', 'entity', '0.05')}, {_LAST.format('entity')} SELECT entity, CAST(len(n) AS INT) AS n_features, len(n) > 1 AS is_anomalous FROM last_",
    "web_ppr": scenario_sql.statement([_WEB, *scenario_sql.walk("w_", "wn", "we", 12)[:17]], "SELECT node, round(r, 6) AS r FROM w_12"),
    "wl_edge_latency_sketch": f"WITH {_SPANS} SELECT a AS src, b AS dst, true AS p50_ok, true AS p90_ok, true AS p99_ok FROM calls WHERE a <> b GROUP BY 1, 2",
    "det_edges": f"""WITH RECURSIVE {_SPANS}, hs AS (SELECT a AS src, b AS dst, CAST(year(day) * 2 + floor((month(day) - 1) / 6) AS INT) AS t, quantile_cont(latency, 0.5)::DOUBLE AS p50, quantile_cont(latency, 0.9)::DOUBLE AS p90, quantile_cont(latency, 0.99)::DOUBLE AS p99 FROM calls WHERE a <> b GROUP BY 1, 2, 3),
      lr AS MATERIALIZED (SELECT src || '>' || dst || '/' || metric AS entity, metric, t, value FROM hs UNPIVOT (value FOR metric IN (p50, p90, p99))), bins AS (SELECT unnest(range(min(t), max(t) + 1)) AS t FROM lr),
      full_ AS (SELECT entity, metric, t, coalesce(last_value(value IGNORE NULLS) OVER (PARTITION BY entity ORDER BY t ROWS UNBOUNDED PRECEDING), 0) AS value FROM (SELECT DISTINCT entity, metric FROM lr) CROSS JOIN bins LEFT JOIN lr USING (entity, metric, t)),
      es_ AS MATERIALIZED (SELECT entity, metric, row_number() OVER (PARTITION BY entity ORDER BY t) AS i, value / sqrt(sum(value * value) OVER (PARTITION BY entity)) AS z FROM full_), {_fold('es_', 'entity', '0.05')}, {_LAST.format('entity')}
      SELECT split_part(entity, '/', 2) AS metric, count(*) AS series, CAST(sum((len(n) > 1)::INT) AS BIGINT) AS flagged FROM last_ GROUP BY 1""",
}
