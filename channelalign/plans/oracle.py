"""SQL of the registered queries, for an engine that knows only the given tables. Planted channels are rebuilt here."""

from __future__ import annotations

HOUR, DAY, MONTH30 = 3_600_000_000, 86_400_000_000, 30 * 86_400_000_000
ORIGIN = 1_704_067_200_000_000

EV = "ev AS (SELECT event_type AS channel, user_id AS src, CAST(NULL AS BIGINT) AS dst, epoch_us(ts) AS us, event_id AS key FROM events)"
LI = "SELECT {by} AS channel, l_suppkey AS src, o_custkey AS dst, epoch_us(l_shipdate) AS us FROM lineitem JOIN orders ON l_orderkey = o_orderkey"


def twin(jitter: int = 31) -> str:
    """tw: the planted events; truth."""
    alias = "1000000 + 2 * ((user_id * 37 + 11) % n) + CASE WHEN user_id % 10 = 0 THEN event_id % 2 ELSE 0 END"
    return f"""nn AS (SELECT max(user_id) + 1 AS n FROM events),
tb AS (SELECT user_id, {alias} AS alias, epoch_us(ts) + (CAST(event_id AS BIGINT) * 7919 % {2 * jitter + 1} - {jitter}) * 1000000 AS us FROM events, nn WHERE event_id % 10 <> 4 AND user_id % 7 <> 3),
tw AS (SELECT 'a' AS channel, user_id AS src, epoch_us(ts) AS us FROM events WHERE event_id % 10 <> 9 AND user_id % 7 <> 5 UNION ALL SELECT 'b', alias, us FROM tb),
truth AS (SELECT DISTINCT user_id AS u, alias AS v FROM tb WHERE user_id % 7 <> 5)"""


def supplier_twin() -> str:
    key = "(CAST(l_orderkey AS BIGINT) * 8 + l_linenumber)"
    alias = f"1000000 + 2 * ((l_suppkey * 37 + 11) % n) + CASE WHEN l_suppkey % 10 = 0 THEN {key} % 2 ELSE 0 END"
    return f"""nn AS (SELECT count(*) * 10 + 1 AS n FROM supplier),
tb AS (SELECT l_suppkey, {alias} AS alias, epoch_us(l_shipdate) + CASE WHEN {key} % 5 = 0 THEN {DAY} ELSE 0 END AS us FROM lineitem, nn WHERE {key} % 10 <> 4 AND l_suppkey % 7 <> 3),
tw AS (SELECT 'a' AS channel, l_suppkey AS src, epoch_us(l_shipdate) AS us FROM lineitem WHERE {key} % 10 <> 9 AND l_suppkey % 7 <> 5 UNION ALL SELECT 'b', alias, us FROM tb),
truth AS (SELECT DISTINCT l_suppkey AS u, alias AS v FROM tb WHERE l_suppkey % 7 <> 5)"""


def bins(width: int = HOUR, of: str = "tw", origin: int | None = None, name: str = "bn", first: bool = False, segment: str | None = None) -> str:
    t0 = f"(SELECT min(us) AS t0 FROM {of})" if origin is None else f"(SELECT CAST({origin} AS BIGINT) AS t0)"
    seg = f", {segment} AS segment" if segment else ""
    return f"""{name}0 AS (SELECT channel, src AS entity, CAST(floor((us - t0) / CAST({width} AS DOUBLE)) AS BIGINT) AS bin, count(*) AS cnt{", min(us) AS first_us" if first else ""} FROM {of}, {t0} WHERE src IS NOT NULL GROUP BY ALL),
{name} AS (SELECT *{seg} FROM {name}0)"""


def pairs(left: str = "a", right: str = "b", seg: bool = False, label: str | None = None, of: str = "bn") -> str:
    k = "segment, " if seg else ""
    on = f"l.bin = r.bin{' AND l.segment = r.segment' if seg else ''}{' AND l.cluster = r.cluster' if label else ''}"
    rows = f"(SELECT * FROM {of} JOIN {label} USING (channel, entity))" if label else of
    return f"""sq AS (SELECT {k}channel, entity, CAST(sum(cnt * cnt) AS BIGINT) AS q FROM {of} GROUP BY ALL),
dt AS (SELECT {'l.segment, ' if seg else ''}l.entity AS u, r.entity AS v, CAST(sum(l.cnt * r.cnt) AS BIGINT) AS dot FROM {rows} l JOIN {rows} r ON {on} AND l.channel = '{left}' AND r.channel = '{right}' GROUP BY ALL),
pr AS (SELECT {'dt.segment, ' if seg else ''}u, v, dot, dot / sqrt(CAST(x.q * y.q AS DOUBLE)) AS sim FROM dt
  JOIN sq x ON x.channel = '{left}' AND x.entity = u{' AND x.segment = dt.segment' if seg else ''} JOIN sq y ON y.channel = '{right}' AND y.entity = v{' AND y.segment = dt.segment' if seg else ''})"""


def best(of: str = "pr", score: str = "sim", name: str = "mt", where: str = "TRUE") -> str:
    return f"""{name} AS (SELECT * FROM (SELECT *, rank() OVER (PARTITION BY u ORDER BY {score} DESC) AS f, rank() OVER (PARTITION BY v ORDER BY {score} DESC) AS b FROM {of} WHERE {where}) WHERE f = 1 AND b = 1)"""


def measures(found: str = "mt", truth: str = "truth") -> str:
    """ms: one row of measures."""
    return f"""fu AS (SELECT DISTINCT u, v FROM {found}), rg AS (SELECT u, v FROM fu INTERSECT SELECT u, v FROM {truth}),
c AS (SELECT (SELECT count(*) FROM fu) AS n_found, (SELECT count(*) FROM rg) AS n_right, (SELECT count(*) FROM {truth}) AS n_true,
  (SELECT count(DISTINCT u) FROM rg) AS ru, (SELECT count(DISTINCT u) FROM {truth}) AS tu, (SELECT count(DISTINCT v) FROM rg) AS rv, (SELECT count(DISTINCT v) FROM {truth}) AS tv),
ms AS (SELECT n_found, n_right, n_true, round(n_right / nullif(n_found, 0), 9) AS ma, round(ru / nullif(tu, 0), 9) AS fnma, round(rv / nullif(tv, 0), 9) AS bnma,
  round(n_right / nullif(n_true, 0), 9) AS recall, round(2 * n_right / nullif(n_found + n_true, 0), 9) AS f1, round(n_right / nullif(n_found + n_true - n_right, 0), 9) AS jaccard FROM c)"""


def maxima(left: str = "a", right: str = "b") -> str:
    """h1 and h0 per segment, with ten draws."""
    return f"""us AS (SELECT DISTINCT segment, entity AS u FROM bn WHERE channel = '{left}'),
vs AS (SELECT segment, v, row_number() OVER (PARTITION BY segment ORDER BY v % 64, v) - 1 AS place, count(*) OVER (PARTITION BY segment) AS total FROM (SELECT DISTINCT segment, entity AS v FROM bn WHERE channel = '{right}')),
h1 AS (SELECT segment, u, coalesce(max(sim), 0.0) AS s FROM us LEFT JOIN pr USING (segment, u) GROUP BY ALL),
tt AS (SELECT segment, max(total) AS total FROM vs GROUP BY ALL),
dr AS (SELECT segment, u, ((u * 7919 + (j + 1) * 104729) % 1000003 * 31337 + u * 613 + j * 86028121) % total AS place FROM us JOIN tt USING (segment), (SELECT unnest(range(0, 10)) AS j)),
h0 AS (SELECT segment, u, max(coalesce(sim, 0.0)) AS s FROM dr JOIN vs USING (segment, place) LEFT JOIN pr USING (segment, u, v) GROUP BY ALL)"""


MODEL = """md AS (SELECT segment, nullif(s1, 0) AS sigma1, nullif(s0, 0) AS sigma0, n1, n0 FROM
  (SELECT segment, sqrt(sum(s * s) / (2 * count(*))) AS s1, count(*) AS n1 FROM h1 GROUP BY ALL) JOIN (SELECT segment, sqrt(sum(s * s) / (2 * count(*))) AS s0, count(*) AS n0 FROM h0 GROUP BY ALL) USING (segment))"""
RATIO = "2 * ln(sigma0 / sigma1) + {s} * {s} / 2 * (1 / (sigma0 * sigma0) - 1 / (sigma1 * sigma1))"
SCORED = f"sc AS (SELECT segment, u, v, sim, {RATIO.format(s='sim')} AS score FROM pr JOIN md USING (segment))"
STATE = "st AS (SELECT u, v, round(sum(score), 6) AS score, count(*) AS n_segments, max(segment) AS last_segment FROM sc GROUP BY ALL)"
WEEK = "CAST(floor(bin / 168.0) AS BIGINT)"
PDF = "{s} / (sigma * sigma) * exp(-{s} * {s} / (2 * sigma * sigma))"


def weekly(*more: str) -> list[str]:
    return [twin(), bins(HOUR, origin=ORIGIN, segment=WEEK), pairs(seg=True), maxima(), *more]


def sweep(state: str = "st", truth: str = "truth") -> str:
    thetas = "(VALUES (-5.0), (0.0), (1.0), (5.0), (10.0), (15.0), (20.0), (30.0))"
    return f"""mt AS (SELECT u, v, score FROM (SELECT *, rank() OVER (PARTITION BY u ORDER BY score DESC) AS f, rank() OVER (PARTITION BY v ORDER BY score DESC) AS b FROM {state}) WHERE f = 1 AND b = 1),
th AS (SELECT CAST(t AS DOUBLE) AS theta FROM {thetas} AS x(t)),
fd AS (SELECT theta, count(*) AS n_found FROM th JOIN mt ON score >= theta GROUP BY ALL),
rt AS (SELECT theta, count(*) AS n_right, count(DISTINCT u) AS ru, count(DISTINCT v) AS rv FROM th JOIN mt ON score >= theta JOIN {truth} USING (u, v) GROUP BY ALL),
tr AS (SELECT count(*) AS n_true, count(DISTINCT u) AS tu, count(DISTINCT v) AS tv FROM {truth}),
ms AS (SELECT theta, coalesce(n_found, 0) AS n_found, coalesce(n_right, 0) AS n_right, n_true, round(coalesce(n_right, 0) / nullif(coalesce(n_found, 0), 0), 9) AS ma,
  round(coalesce(ru, 0) / tu, 9) AS fnma, round(coalesce(rv, 0) / tv, 9) AS bnma, round(coalesce(n_right, 0) / n_true, 9) AS recall,
  round(2 * coalesce(n_right, 0) / (coalesce(n_found, 0) + n_true), 9) AS f1, round(coalesce(n_right, 0) / (coalesce(n_found, 0) + n_true - coalesce(n_right, 0)), 9) AS jaccard
  FROM th LEFT JOIN fd USING (theta) LEFT JOIN rt USING (theta), tr)"""


def sql(parts: list[str], last: str) -> str:
    return "WITH " + ",\n".join(parts) + "\n" + last


FEATURES = f"""sp AS (SELECT min(us) AS t0, CAST((max(us) - min(us)) // {HOUR} + 1 AS BIGINT) AS nb FROM ev),
lg AS (SELECT *, lag(bin) OVER w AS pb, lag(cnt) OVER w AS pc, lead(bin) OVER w AS xb FROM bn, sp WINDOW w AS (PARTITION BY channel, entity ORDER BY bin)),
rw AS (SELECT channel, entity, sum(cnt) / max(nb) AS aec, sum(CASE WHEN pb IS NULL THEN CASE WHEN bin > 0 THEN cnt ELSE 0 END WHEN bin - pb = 1 THEN abs(cnt - pc) ELSE cnt + pc END + CASE WHEN xb IS NULL AND bin < nb - 1 THEN cnt ELSE 0 END) / greatest(max(nb) - 1, 1) AS dec,
  CAST(min(first_us) - max(t0) AS DOUBLE) AS ie, sum(cnt) / count(*) AS aec_active FROM lg GROUP BY ALL),
ft AS (SELECT channel, entity, coalesce(aec / nullif((SELECT max(aec) FROM rw), 0), 0) AS f0, coalesce(dec / nullif((SELECT max(dec) FROM rw), 0), 0) AS f1, coalesce(ie / nullif((SELECT max(ie) FROM rw), 0), 0) AS f2 FROM rw)"""
RAW = [EV, bins(HOUR, "ev", first=True), FEATURES]
BAND = "lb AS (SELECT channel, entity, CAST(CASE WHEN sum(cnt) >= 55 THEN 1 ELSE 0 END + CASE WHEN sum(cnt) >= 70 THEN 1 ELSE 0 END AS INTEGER) AS cluster FROM bn GROUP BY ALL)"
TWIN = [twin(), bins()]
CENTRES = ((0.2, 0.2, 0.1), (0.5, 0.5, 0.2), (0.8, 0.8, 0.3))
_GAP = "(f0 - {0}) * (f0 - {0}) + (f1 - {1}) * (f1 - {1}) + (f2 - {2}) * (f2 - {2})"


def _correlation() -> str:
    return sql([EV, twin(), "al AS (SELECT channel, src, us FROM ev UNION ALL SELECT channel, src, us FROM tw)", bins(HOUR, "al"),
        f"sp AS (SELECT CAST((max(us) - min(us)) // {HOUR} + 1 AS BIGINT) AS n FROM al)", "tt AS (SELECT channel, bin, CAST(sum(cnt) AS BIGINT) AS t FROM bn GROUP BY ALL)",
        "ss AS (SELECT channel, CAST(sum(t) AS BIGINT) AS s, CAST(sum(t * t) AS BIGINT) AS q FROM tt GROUP BY ALL)",
        'pp AS (SELECT x.channel AS l, y.channel AS r, CAST(sum(x.t * y.t) AS BIGINT) AS p FROM tt x JOIN tt y USING (bin) WHERE x.channel < y.channel GROUP BY ALL)'],
        'SELECT x.channel AS "left", y.channel AS "right", round((n * coalesce(p, 0) - x.s * y.s) / nullif(sqrt(CAST(n * x.q - x.s * x.s AS DOUBLE)) * sqrt(CAST(n * y.q - y.s * y.s AS DOUBLE)), 0), 6) AS corr, round(coalesce(p, 0) / sqrt(CAST(x.q * y.q AS DOUBLE)), 6) AS cos FROM ss x JOIN ss y ON x.channel < y.channel LEFT JOIN pp ON l = x.channel AND r = y.channel, sp')


def _sensitivity() -> str:
    parts, rows = [], []
    for jitter in (1, 31):
        for seconds in (3, 60, 3600, 21600):
            inner = sql([twin(jitter), bins(seconds * 1_000_000), pairs(), best(), measures()], f"SELECT CAST({jitter} AS INTEGER) AS jitter_s, CAST({seconds} AS INTEGER) AS width_s, n_found, ma, fnma, bnma FROM ms")
            rows.append(f"SELECT * FROM ({inner})")
    return "\nUNION ALL\n".join(parts + rows)


def _ablation() -> str:
    rows = []
    for way, where in (("intersect", "f = 1 AND b = 1"), ("union", "f = 1 OR b = 1"), ("forward", "f = 1"), ("backward", "b = 1"), ("top2", "tf <= 2 AND tb2 <= 2"), ("threshold", "sim >= 0.04")):
        rank = "SELECT *, rank() OVER (PARTITION BY u ORDER BY sim DESC) AS f, rank() OVER (PARTITION BY v ORDER BY sim DESC) AS b, row_number() OVER (PARTITION BY u ORDER BY sim DESC, v) AS tf, row_number() OVER (PARTITION BY v ORDER BY sim DESC, u) AS tb2 FROM pr"
        rows.append("SELECT * FROM (" + sql([twin(), bins(3_000_000), pairs(), f"mt AS (SELECT * FROM ({rank}) WHERE {where})", measures()], f"SELECT '{way}' AS way, n_found, n_right, ma, fnma, bnma FROM ms") + ")")
    return "\nUNION ALL\n".join(rows)


def _units() -> str:
    base = [twin(), bins(), pairs(), best(), "fw AS (SELECT u, v FROM (SELECT *, rank() OVER (PARTITION BY u ORDER BY sim DESC) AS f FROM pr) WHERE f = 1)", "bw AS (SELECT u, v FROM (SELECT *, rank() OVER (PARTITION BY v ORDER BY sim DESC) AS b FROM pr) WHERE b = 1)"]
    rows = []
    for stage, side, unit, found in (("final", "forward", "entity", "mt"), ("final", "backward", "entity", "mt"), ("final", "forward", "pair", "mt"), ("directional", "forward", "entity", "fw"), ("directional", "backward", "entity", "bw")):
        what = {"forward": "u", "backward": "v"}[side] if unit == "entity" else "(u, v)"
        rows.append(f"SELECT '{stage}' AS stage, '{side}' AS side, '{unit}' AS unit, t AS n_true, t - h AS n_missed, round(1 - (t - h) / t, 9) AS accuracy FROM (SELECT (SELECT count(DISTINCT {what}) FROM truth) AS t, (SELECT count(DISTINCT {what}) FROM truth JOIN {found} USING (u, v)) AS h)")
    return sql(base, "\nUNION ALL\n".join(rows))


_PAIRED = [*TWIN, pairs()]
_RANKED = "rk AS (SELECT *, row_number() OVER (PARTITION BY u ORDER BY sim DESC, v) AS tf, row_number() OVER (PARTITION BY v ORDER BY sim DESC, u) AS tb, rank() OVER (PARTITION BY u ORDER BY sim DESC) AS f, rank() OVER (PARTITION BY v ORDER BY sim DESC) AS b FROM pr)"
_PAIR = "u, v, dot, round(sim, 9) AS sim"

ORACLES: dict[str, str] = {
    "profile_channels": sql([EV, f"al AS (SELECT channel, src, us FROM ev UNION ALL SELECT 'orders', o_custkey, epoch_us(o_orderdate) FROM orders UNION ALL SELECT channel, src, us FROM ({LI.format(by='l_returnflag')}))"], "SELECT channel, count(*) AS n_events, count(DISTINCT src) AS n_entities, min(us) AS first_us, max(us) AS last_us FROM al GROUP BY channel"),
    "profile_rollup": sql([EV], f"SELECT coalesce(channel, 'all') AS channel, coalesce(us // {DAY}, -1) AS day, count(*) AS n_events, count(DISTINCT src) AS n_entities FROM ev GROUP BY ROLLUP (channel, us // {DAY})"),
    "profile_sketch": sql([EV], "SELECT channel, count(DISTINCT src) AS n_entities, TRUE AS near_enough FROM ev GROUP BY channel"),
    "span_events": sql([EV], f"SELECT min(us) AS t0_us, max(us) AS last_us, CAST((max(us) - min(us)) // {HOUR} + 1 AS BIGINT) AS n_bins FROM ev"),
    "bin_events_hour": sql([EV, bins(HOUR, "ev")], "SELECT * FROM bn"),
    "bin_events_3s": sql([EV, bins(3_000_000, "ev")], "SELECT * FROM bn"),
    "bin_lineitem_source_role": sql([f"li AS ({LI.format(by='l_returnflag')})", bins(MONTH30, "li")], "SELECT * FROM bn"),
    "bin_lineitem_target_role": sql([f"l0 AS ({LI.format(by='l_returnflag')})", "li AS (SELECT channel, dst AS src, us FROM l0)", bins(MONTH30, "li")], "SELECT * FROM bn"),
    "bin_lineitem_both_roles": sql([f"l0 AS ({LI.format(by='l_linestatus')})", "li AS (SELECT channel, src, us FROM l0 UNION ALL SELECT channel, dst, us FROM l0)", bins(MONTH30, "li")], "SELECT * FROM bn"),
    "bin_stream_equiv": sql([EV, bins(HOUR, "ev", 0)], "SELECT * FROM bn"),
    "planted_truth": sql([twin()], "SELECT u, v FROM truth"),
    "sparsity": sql([EV, bins(HOUR, "ev"), f"sp AS (SELECT CAST((max(us) - min(us)) // {HOUR} + 1 AS BIGINT) AS n_bins FROM ev)"], "SELECT channel, count(DISTINCT entity) AS n_entities, count(*) AS nnz, CAST(sum(cnt) AS BIGINT) AS n_events, any_value(n_bins) AS n_bins, round(count(*) / (count(DISTINCT entity) * any_value(n_bins)), 9) AS fill FROM bn, sp GROUP BY channel"),
    "vectors_arrays": sql([EV, "e2 AS (SELECT * FROM ev WHERE channel IN ('view', 'click'))", bins(DAY, "e2")], "SELECT channel, entity, string_agg(CAST(bin AS VARCHAR), ',' ORDER BY bin) AS bins, string_agg(CAST(cnt AS VARCHAR), ',' ORDER BY bin) AS cnts, CAST(sum(cnt * cnt) AS BIGINT) AS sq_norm, CAST(sum(cnt) AS BIGINT) AS n_events FROM bn GROUP BY channel, entity"),
    "avg_count": sql(RAW, "SELECT channel, entity, round(aec, 9) AS aec, round(aec_active, 9) AS aec_active FROM rw"),
    "edge_delta_abs": sql(RAW, 'SELECT channel, entity, round("dec", 9) AS "dec" FROM rw'),
    "edge_delta_signed": sql(RAW, 'SELECT channel, entity, round((sum(CASE WHEN bin = nb - 1 THEN cnt ELSE 0 END) - sum(CASE WHEN bin = 0 THEN cnt ELSE 0 END)) / greatest(max(nb) - 1, 1), 9) AS "dec" FROM bn, sp GROUP BY channel, entity'),
    "first_event": sql(RAW, "SELECT channel, entity, CAST(ie AS BIGINT) AS ie FROM rw"),
    "reduced_features": sql(RAW, "SELECT channel, entity, round(f0, 9) AS f0, round(f1, 9) AS f1, round(f2, 9) AS f2 FROM ft"),
    "reduced_with_attributes": sql([*RAW, "att AS (SELECT event_type AS channel, user_id AS entity, avg(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS k FROM events GROUP BY ALL)"], "SELECT channel, entity, round(f0, 9) AS f0, round(f1, 9) AS f1, round(f2, 9) AS f2, round(coalesce(k / nullif((SELECT max(k) FROM att), 0), 0), 9) AS f3 FROM ft JOIN att USING (channel, entity)"),
    "laplacian_small": sql([EV, bins(HOUR, "ev"), "tt AS (SELECT channel, bin, CAST(sum(cnt) AS BIGINT) AS t FROM bn GROUP BY ALL)", "ss AS (SELECT channel, CAST(sum(t * t) AS BIGINT) AS q, row_number() OVER (ORDER BY channel) - 1 AS n FROM tt GROUP BY channel)",
        "pp AS (SELECT x.channel AS l, y.channel AS r, CAST(sum(x.t * y.t) AS BIGINT) AS p FROM tt x JOIN tt y USING (bin) WHERE x.channel < y.channel GROUP BY ALL)",
        "w AS (SELECT x.n AS i, y.n AS j, coalesce(p, 0) / sqrt(CAST(x.q * y.q AS DOUBLE)) AS w FROM ss x JOIN ss y ON x.channel < y.channel LEFT JOIN pp ON l = x.channel AND r = y.channel)", "bo AS (SELECT i, j, w FROM w UNION ALL SELECT j, i, w FROM w)"],
        "SELECT i, j, round(-w, 6) AS l FROM bo UNION ALL SELECT i, i, round(sum(w), 6) FROM bo GROUP BY i"),
    "partition_subsets": sql([EV], "SELECT channel, src AS entity, CAST(CAST('0x' || substr(md5(channel || ':' || CAST(src AS VARCHAR) || ':7'), 1, 8) AS BIGINT) % 22 AS INTEGER) AS subset FROM (SELECT DISTINCT channel, src FROM ev)"),
    "label_nearest_fixed_centroids": sql([*RAW, "ds AS (SELECT channel, entity, " + ", ".join(f"{_GAP.format(*c)} AS d{i}" for i, c in enumerate(CENTRES)) + " FROM ft)"], "SELECT channel, entity, CAST(CASE WHEN d0 <= d1 AND d0 <= d2 THEN 0 WHEN d1 <= d2 THEN 1 ELSE 2 END AS INTEGER) AS cluster FROM ds"),
    "cluster_balance": sql([*TWIN, BAND], "SELECT cluster, channel, count(*) AS n, round(count(*) / any_value(t), 9) AS share FROM lb JOIN (SELECT channel, count(*) AS t FROM lb GROUP BY channel) USING (channel) GROUP BY cluster, channel"),
    "comparisons_kept": sql([*TWIN, BAND, "sz AS (SELECT cluster, count(*) FILTER (channel = 'a') AS a, count(*) FILTER (channel = 'b') AS b FROM lb GROUP BY cluster)", "kk AS (SELECT CAST(sum(a * b) AS BIGINT) AS kept, CAST(sum(a) * sum(b) AS BIGINT) AS all_pairs FROM sz)"], "SELECT kept, all_pairs, round(kept / all_pairs, 9) AS kept_share, round(all_pairs / kept, 9) AS ideal_speed_up FROM kk"),
    "partial_products": sql([*TWIN, BAND, "sd AS (SELECT bin, cluster, count(*) FILTER (channel = 'a') AS a, count(*) FILTER (channel = 'b') AS b FROM bn JOIN lb USING (channel, entity) GROUP BY ALL)"], "SELECT CAST(sum(a * b) AS BIGINT) AS products, max(a * b) AS busiest, count(*) FILTER (a * b > 0) AS shared_bins FROM sd"),
    "cocluster_recall": sql([*TWIN, BAND], "SELECT count(*) AS n_true, count(*) FILTER (x.cluster = y.cluster) AS n_together, round(count(*) FILTER (x.cluster = y.cluster) / count(*), 9) AS recall FROM truth JOIN lb x ON x.channel = 'a' AND x.entity = u JOIN lb y ON y.channel = 'b' AND y.entity = v"),
    **dict.fromkeys(("cosine_all", "cosine_blocks", "cosine_salted", "pipeline_all"), sql(_PAIRED, f"SELECT {_PAIR} FROM pr")),
    "cosine_within_band": sql([*TWIN, BAND, pairs(label="lb")], f"SELECT {_PAIR} FROM pr"),
    "cosine_pruned": sql(_PAIRED, f"SELECT {_PAIR} FROM pr WHERE sim >= 0.3"),
    "cosine_all_channels": sql([EV, "e2 AS (SELECT * FROM ev WHERE channel IN ('view', 'click', 'purchase'))", bins(HOUR, "e2"), "sq AS (SELECT channel, entity, CAST(sum(cnt * cnt) AS BIGINT) AS q FROM bn GROUP BY ALL)", "dt AS (SELECT l.channel AS lc, r.channel AS rc, l.entity AS u, r.entity AS v, CAST(sum(l.cnt * r.cnt) AS BIGINT) AS dot FROM bn l JOIN bn r ON l.bin = r.bin AND l.channel < r.channel GROUP BY ALL)"], 'SELECT lc AS "left", rc AS "right", u, v, dot, round(dot / sqrt(CAST(x.q * y.q AS DOUBLE)), 9) AS sim FROM dt JOIN sq x ON x.channel = lc AND x.entity = u JOIN sq y ON y.channel = rc AND y.entity = v WHERE dot / sqrt(CAST(x.q * y.q AS DOUBLE)) >= 0.2'),
    "jaccard_bins": sql([*TWIN, "nc AS (SELECT channel, entity, count(*) AS n FROM bn GROUP BY ALL)", "bo AS (SELECT l.entity AS u, r.entity AS v, count(*) AS bth FROM bn l JOIN bn r ON l.bin = r.bin AND l.channel = 'a' AND r.channel = 'b' GROUP BY ALL)"], 'SELECT u, v, bth AS shared, round(bth / (x.n + y.n - bth), 9) AS jaccard FROM bo JOIN nc x ON x.channel = \'a\' AND x.entity = u JOIN nc y ON y.channel = \'b\' AND y.entity = v'),
    "near_counts": sql([twin()], "SELECT x.src AS u, y.src AS v, count(*) AS n FROM tw x JOIN tw y ON x.channel = 'a' AND y.channel = 'b' AND y.us BETWEEN x.us - 62000000 AND x.us + 62000000 GROUP BY ALL"),
    "last_before": sql([EV], "SELECT x.key, x.src, x.us, coalesce(y.us, -1) AS before_us FROM (SELECT * FROM ev WHERE channel = 'view') x ASOF LEFT JOIN (SELECT src, us FROM ev WHERE channel = 'click') y ON x.src = y.src AND x.us >= y.us"),
    "channel_correlation": _correlation(),
    "match_threshold": sql(_PAIRED, "SELECT u, v, round(sim, 9) AS sim FROM pr WHERE sim >= 0.5"),
    "match_best": sql([*_PAIRED, best(where="sim >= 0.3")], "SELECT u, v, round(sim, 9) AS sim FROM mt"),
    "match_top3": sql([*_PAIRED, _RANKED], "SELECT u, v, round(sim, 9) AS sim FROM rk WHERE tf <= 3 AND tb <= 3"),
    "forward": sql([*_PAIRED, _RANKED], "SELECT u, v, round(sim, 9) AS sim FROM rk WHERE f = 1"),
    "backward": sql([*_PAIRED, _RANKED], "SELECT u, v, round(sim, 9) AS sim FROM rk WHERE b = 1"),
    "reconciled": sql([*_PAIRED, _RANKED], "SELECT u, v FROM rk WHERE f = 1 INTERSECT SELECT u, v FROM rk WHERE b = 1"),
    "reconciled_union": sql([*_PAIRED, _RANKED], "SELECT u, v, round(sim, 9) AS sim FROM rk WHERE f = 1 OR b = 1"),
    "pipeline_unclustered": sql([*_PAIRED, best()], f"SELECT {_PAIR} FROM mt"),
    "h1_maxima": sql(weekly(), "SELECT segment, u, round(s, 9) AS s FROM h1"),
    "h0_maxima": sql(weekly(), "SELECT segment, u, round(s, 9) AS s FROM h0"),
    "h0_matched": sql(weekly("r2 AS (SELECT segment, u, sim FROM (SELECT *, row_number() OVER (PARTITION BY segment, u ORDER BY sim DESC, v) AS r FROM pr) WHERE r = 2)"), "SELECT segment, u, round(coalesce(sim, 0.0), 9) AS s FROM us LEFT JOIN r2 USING (segment, u)"),
    "rayleigh_fit": sql(weekly(MODEL), "SELECT segment, round(sigma1, 6) AS sigma1, round(sigma0, 6) AS sigma0, n1, n0 FROM md"),
    "rayleigh_hist": sql(weekly("hh AS (SELECT 'H1' AS side, s FROM h1 WHERE segment = 1 UNION ALL SELECT 'H0', s FROM h0 WHERE segment = 1)", "ff AS (SELECT side, sqrt(sum(s * s) / (2 * count(*))) AS sigma, count(*) AS n FROM hh GROUP BY side)", "bk AS (SELECT side, CAST(least(floor(s * 20), 19) AS BIGINT) AS bucket, count(*) AS c FROM hh GROUP BY ALL)"), f"SELECT side, bucket, round(bucket / 20, 6) AS low, round(c * 20 / n, 6) AS observed, round({PDF.format(s='((bucket + 0.5) / 20)')}, 6) AS fitted FROM bk JOIN ff USING (side)"),
    "rayleigh_ks": sql(weekly("ff AS (SELECT segment, sqrt(sum(s * s) / (2 * count(*))) AS sigma FROM h1 GROUP BY ALL)", "cc AS (SELECT segment, s, count(*) AS c FROM h1 GROUP BY ALL)", "kk AS (SELECT *, sum(c) OVER (PARTITION BY segment ORDER BY s) AS k, sum(c) OVER (PARTITION BY segment) AS n FROM cc)"), "SELECT segment, round(max(greatest(abs(k / n - (1 - exp(-s * s / (2 * sigma * sigma)))), abs((k - c) / n - (1 - exp(-s * s / (2 * sigma * sigma)))))), 6) AS ks FROM kk JOIN ff USING (segment) GROUP BY segment"),
    "overlap": sql(weekly(MODEL, "bs AS (SELECT segment, greatest(sigma1, sigma0) AS g, least(sigma1, sigma0) AS l FROM md)", "xx AS (SELECT *, 4 * ln(g / l) / (1 / (l * l) - 1 / (g * g)) AS x FROM bs)"), "SELECT segment, round(CASE WHEN g = l THEN 1.0 ELSE 1 - exp(-x / (2 * g * g)) + exp(-x / (2 * l * l)) END, 6) AS overlap FROM xx"),
    "score_segment": sql(weekly(MODEL, SCORED), "SELECT segment, u, v, round(score, 6) AS score FROM sc"),
    "score_forms": sql(weekly(MODEL, SCORED), "SELECT u, v, round(ln(greatest(sim / (sigma1 * sigma1) * exp(-sim * sim / (2 * sigma1 * sigma1)), 1e-300)), 6) AS log_p1, round(-ln(1 + exp(-score)), 6) AS log_posterior FROM sc JOIN md USING (segment) WHERE segment = 1"),
    **dict.fromkeys(("score_accumulated", "incremental_equals_batch", "stream_equals_batch"), sql(weekly(MODEL, SCORED, STATE), "SELECT * FROM st")),
    "score_absent_zero": sql(weekly(MODEL, SCORED, "kn AS (SELECT DISTINCT u, v FROM pr)", "sl AS (SELECT segment, u, v FROM kn JOIN us USING (u) JOIN vs USING (segment, v) ANTI JOIN pr USING (segment, u, v))", f"al AS (SELECT segment, u, v, score FROM sc UNION ALL SELECT segment, u, v, {RATIO.format(s='0.0')} FROM sl JOIN md USING (segment))"), "SELECT u, v, round(sum(score), 6) AS score, count(*) AS n_segments, max(segment) AS last_segment FROM al GROUP BY u, v"),
    "score_trajectory": sql(weekly(MODEL, SCORED), "SELECT segment, u, v, round(score, 6) AS score, round(sum(score) OVER (PARTITION BY u, v ORDER BY segment), 6) AS total FROM sc"),
    "score_matches": sql(weekly(MODEL, SCORED, STATE, best("st", "score", where="score >= 1.0")), "SELECT u, v, score FROM mt"),
    "metrics_final": sql([*_PAIRED, best(), measures()], "SELECT * FROM ms"),
    "metrics_units": _units(),
    "metrics_sweep_weekly": sql(weekly(MODEL, SCORED, STATE, sweep()), "SELECT * FROM ms"),
    "metrics_sweep_monthly_supplier": sql([supplier_twin(), bins(DAY, origin=0, segment="CAST(year(DATE '1970-01-01' + CAST(bin AS INTEGER)) - 1970 AS BIGINT) * 12 + month(DATE '1970-01-01' + CAST(bin AS INTEGER)) - 1"), pairs(seg=True), maxima(), MODEL, SCORED, STATE, sweep()], "SELECT * FROM ms"),
    "jaccard_found_truth": sql([*_PAIRED, best()], "SELECT n_both, n_either, round(n_both / n_either, 9) AS jaccard FROM (SELECT (SELECT count(*) FROM (SELECT u, v FROM mt INTERSECT SELECT u, v FROM truth)) AS n_both, (SELECT count(*) FROM (SELECT u, v FROM mt UNION SELECT u, v FROM truth)) AS n_either)"),
    "random_match": sql([*TWIN, "ru AS (SELECT u, row_number() OVER (ORDER BY md5(CAST(u AS VARCHAR) || ':0')) AS r FROM (SELECT DISTINCT entity AS u FROM bn WHERE channel = 'a'))", "rv AS (SELECT v, row_number() OVER (ORDER BY md5(CAST(v AS VARCHAR) || ':0')) AS r FROM (SELECT DISTINCT entity AS v FROM bn WHERE channel = 'b'))", "mt AS (SELECT u, v FROM ru JOIN rv USING (r))", measures()], "SELECT * FROM ms"),
    "negative_control": sql([EV, "tw AS (SELECT channel, src, us FROM ev WHERE channel IN ('view', 'click'))", bins(HOUR, origin=ORIGIN, segment=WEEK), pairs("view", "click", seg=True), maxima("view", "click"), MODEL, SCORED, STATE, "truth AS (SELECT DISTINCT src AS u, src AS v FROM tw)", sweep()], "SELECT * FROM ms"),
    "sensitivity_width": _sensitivity(),
    "ablation_matching": _ablation(),
    "pipeline_segments": sql(weekly(), "SELECT 1"),
    "pipeline_all_channels": sql([EV, bins(HOUR, "ev"), "sq AS (SELECT channel, entity, CAST(sum(cnt * cnt) AS BIGINT) AS q FROM bn GROUP BY ALL)", "dt AS (SELECT l.channel AS lc, r.channel AS rc, l.entity AS u, r.entity AS v, CAST(sum(l.cnt * r.cnt) AS BIGINT) AS dot FROM bn l JOIN bn r ON l.bin = r.bin AND l.channel < r.channel GROUP BY ALL)", "pr AS (SELECT lc, rc, u, v, dot / sqrt(CAST(x.q * y.q AS DOUBLE)) AS sim FROM dt JOIN sq x ON x.channel = lc AND x.entity = u JOIN sq y ON y.channel = rc AND y.entity = v)", "rk AS (SELECT *, rank() OVER (PARTITION BY lc, rc, u ORDER BY sim DESC) AS f, rank() OVER (PARTITION BY lc, rc, v ORDER BY sim DESC) AS b FROM pr)"], 'SELECT lc AS "left", rc AS "right", u, v, round(sim, 9) AS sim FROM rk WHERE f = 1 AND b = 1'),
}
# Segments from the epoch of the unpinned pipeline: weeks since 1970.
ORACLES["pipeline_segments"] = sql([twin(), bins(HOUR, origin=0, segment=WEEK), pairs(seg=True), maxima(), MODEL, SCORED, "st AS (SELECT u, v, sum(score) AS score FROM sc GROUP BY ALL)", best("st", "score", where="score >= 1.0"), measures()], "SELECT * FROM ms")
del ORACLES["pipeline_all"]
# Draws of the other side, and of pairs from all.
_DRAW = "((({u}) * 7919 + (j + 1) * 104729 + {seed} * 15485863) % 1000003 * 31337 + ({u}) * 613 + j * 86028121) % {total}"
_PLACED_U = "nu AS (SELECT segment, u, row_number() OVER (PARTITION BY segment ORDER BY u % 64, u) - 1 AS place, count(*) OVER (PARTITION BY segment) AS total FROM us)"
_TEN = "(SELECT unnest(range(0, 10)) AS j)"
ORACLES["h0_by_right"] = sql(weekly(_PLACED_U, "ut AS (SELECT segment, max(total) AS t FROM nu GROUP BY ALL)", f"dv AS (SELECT segment, v, {_DRAW.format(u='v', seed=0, total='t')} AS place FROM vs JOIN ut USING (segment), {_TEN})"), "SELECT segment, v, round(max(coalesce(sim, 0.0)), 9) AS s FROM dv JOIN nu USING (segment, place) LEFT JOIN pr USING (segment, u, v) GROUP BY segment, v")
ORACLES["h0_pool"] = sql(
    weekly(_PLACED_U, "ut AS (SELECT segment, max(total) AS t FROM nu GROUP BY ALL)", f"dp AS (SELECT segment, u AS own, {_DRAW.format(u='u', seed=0, total='total')} AS vp, {_DRAW.format(u='u', seed=1, total='t')} AS up FROM us JOIN tt USING (segment) JOIN ut USING (segment), {_TEN})"),
    "SELECT dp.segment, own AS u, round(max(coalesce(sim, 0.0)), 9) AS s FROM dp JOIN vs ON vs.segment = dp.segment AND vs.place = vp JOIN nu ON nu.segment = dp.segment AND nu.place = up LEFT JOIN pr ON pr.segment = dp.segment AND pr.u = nu.u AND pr.v = vs.v GROUP BY dp.segment, own",
)
ORACLES["stream_split_segments"] = ORACLES["stream_equals_batch"]
ORACLES["metrics_sweep_28d_supplier"] = sql([supplier_twin(), bins(DAY, origin=0, segment="CAST(floor(bin / 28.0) AS BIGINT)"), pairs(seg=True), maxima(), MODEL, SCORED, STATE, sweep()], "SELECT * FROM ms")
# Weekly segments within activity bands: fb are all bins, bn those of the training sample.
_SAMPLED = "bn AS (SELECT * FROM fb WHERE channel = 'b' OR ((entity * 7919 + 104729) % 1000003 * 31337 + 613) % 1000003 / 1000003.0 < 0.2)"
_BANDED = [twin(), bins(HOUR, origin=0, segment=WEEK, name="fb"), BAND.replace("FROM bn", "FROM fb"), _SAMPLED, "lf AS (SELECT fb.*, cluster FROM fb JOIN lb USING (channel, entity))"]
ORACLES["pipeline_segments_clustered"] = sql(
    [
        *_BANDED, pairs(seg=True), maxima(), MODEL, "sf AS (SELECT segment, channel, entity, CAST(sum(cnt * cnt) AS BIGINT) AS q FROM fb GROUP BY ALL)",
        "df AS (SELECT l.segment, l.entity AS u, r.entity AS v, CAST(sum(l.cnt * r.cnt) AS BIGINT) AS dot FROM lf l JOIN lf r ON l.bin = r.bin AND l.segment = r.segment AND l.cluster = r.cluster AND l.channel = 'a' AND r.channel = 'b' GROUP BY ALL)",
        "pf AS (SELECT df.segment, u, v, dot / sqrt(CAST(x.q * y.q AS DOUBLE)) AS sim FROM df JOIN sf x ON x.channel = 'a' AND x.entity = u AND x.segment = df.segment JOIN sf y ON y.channel = 'b' AND y.entity = v AND y.segment = df.segment)",
        SCORED.replace("FROM pr", "FROM pf"), "st AS (SELECT u, v, sum(score) AS score FROM sc GROUP BY ALL)", best("st", "score", where="score >= 1.0"), measures(),
    ], "SELECT * FROM ms",
)
_PRODUCTS = "(SELECT CAST(sum(a * b) AS BIGINT) FROM (SELECT count(*) FILTER (channel = 'a') AS a, count(*) FILTER (channel = 'b') AS b FROM {0} GROUP BY {1})) AS {2}"
ORACLES["products_segments_clustered"] = sql(_BANDED, "SELECT " + ", ".join(_PRODUCTS.format(*x) for x in (("fb", "segment, bin", "unclustered"), ("lf", "segment, bin, cluster", "clustered"), ("bn", "segment, bin", "training"))))
