"""DuckDB SQL for the queries that SQL can express, on the same tables."""

from __future__ import annotations

# Fixed values, as in the fixtures: hundredths of profile, seasons and week.
_PROFILE = "[79,78,77,84,99,130,169,176,169,160,150,140,135,130,130,140,160,190,210,215,200,170,130,95]"
_SEASON = "[200,190,150,100,70,60,90,140,120,80,70,160]"
_MILD = "[120,115,105,95,90,100,125,130,110,95,100,115]"
_WEEK = "[100,104,106,105,110,80,70]"

_HOURLY = """hourly AS (
  SELECT floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600)::BIGINT AS tick, (sum(round(value * 100)::BIGINT)::DOUBLE / 100.0) AS v
  FROM events GROUP BY 1),
filled AS (SELECT r.range AS tick, v IS NULL AS was_missing, coalesce(v, 0.0) AS v FROM range(720) r LEFT JOIN hourly h ON h.tick = r.range)"""


def _z(source: str, key: str, scope: str = "") -> str:
    """CTE z: robust z of source.v, clipped."""
    return f"""med AS (SELECT median(v) AS m FROM {source}), dev AS (SELECT median(abs(v - m)) AS d FROM {source}, med),
z AS (SELECT {key}, greatest(-3.0, least(3.0, coalesce((v - m) / nullif(d, 0.0), 0.0))) AS z FROM {source}, med, dev)"""


def _pollute(source: str, out: str) -> str:
    return f"""{out} AS (SELECT 'all' AS series_id, tick, y_true, bad AS is_polluted, style::INTEGER AS style,
  CASE WHEN NOT bad THEN y_true WHEN style = 0 THEN 0.0 WHEN style = 1 THEN y_true * 2.0 ELSE y_true * 0.5 END AS y
  FROM (SELECT *, (31 * tick * tick + 17 * tick + 7) % 10007 < 500 AS bad, ((13 * tick * tick + 5 * tick + 3) % 1009) % 3 AS style FROM {source}))"""


_BAND = "CASE WHEN p < 100 THEN 0 WHEN p < 140 THEN 1 WHEN p < 170 THEN 2 ELSE 3 END"
_MONTH = f"""{_HOURLY}, {_z('filled', 'tick')},
month0 AS (SELECT tick, {_PROFILE}[(tick % 24 + 1)::INTEGER]::DOUBLE / 100.0 * (1.0::DOUBLE + 0.03::DOUBLE * z) AS y_true FROM z),
{_pollute('month0', 'month1')},
month AS (SELECT *, (tick % 24)::INTEGER AS slot, tick // 24 AS period_ix, {_BAND.replace('p <', _PROFILE + '[(tick % 24 + 1)::INTEGER] <')} AS vp_id FROM month1)"""


def _days(first: str, n: int) -> str:
    return f"""daily AS (SELECT floor((epoch(l_shipdate) - epoch(TIMESTAMP '{first}')) / 86400)::BIGINT AS day,
  sum(round(l_quantity::DOUBLE * 100)::BIGINT)::DOUBLE / 100.0 AS v FROM lineitem GROUP BY 1),
days AS (SELECT r.range AS day, coalesce(v, 0.0) AS v FROM range({n}) r LEFT JOIN daily d ON d.day = r.range)"""


def _year(season: str) -> str:
    return f"""{_days('1997-01-01', 365)}, {_z('days', 'day')},
year0 AS (SELECT day * 24 + h.range AS tick, {_PROFILE}[(h.range + 1)::INTEGER]::DOUBLE / 100.0
    * ({season}[month(DATE '1997-01-01' + day::INTEGER)]::DOUBLE / 100.0)
    * (1.0::DOUBLE + 0.02::DOUBLE * z + 0.06::DOUBLE * (((37 * (day * 24 + h.range) * (day * 24 + h.range) + 11 * (day * 24 + h.range) + 5) % 9973)::DOUBLE / 9973.0 - 0.5::DOUBLE)) AS y_true
  FROM z, range(24) h),
{_pollute('year0', 'year1')},
year AS (SELECT *, (tick % 24)::INTEGER AS slot, tick // 24 AS period_ix, month(DATE '1997-01-01' + (tick // 24)::INTEGER) AS vld_id,
  {_BAND.replace('p <', _PROFILE + '[(tick % 24 + 1)::INTEGER] <')} AS vp_id FROM year1)"""


_YEAR = _year(_SEASON)
_FLEET = f"""typed AS (SELECT event_type AS series_id, floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600)::BIGINT AS tick,
  sum(round(value * 100)::BIGINT)::DOUBLE / 100.0 AS v FROM events GROUP BY 1, 2),
names AS (SELECT series_id, row_number() OVER (ORDER BY series_id) - 1 AS ix FROM (SELECT DISTINCT event_type AS series_id FROM events)),
full0 AS (SELECT n.series_id, ix, r.range AS tick, coalesce(v, 0.0) AS v FROM names n CROSS JOIN range(720) r LEFT JOIN typed t ON t.series_id = n.series_id AND t.tick = r.range),
med AS (SELECT series_id, median(v) AS m FROM full0 GROUP BY 1),
dev AS (SELECT series_id, median(abs(v - m)) AS d FROM full0 JOIN med USING (series_id) GROUP BY 1),
fz AS (SELECT series_id, ix, tick, greatest(-3.0, least(3.0, coalesce((v - m) / nullif(d, 0.0), 0.0))) AS z FROM full0 JOIN med USING (series_id) JOIN dev USING (series_id)),
f0 AS (SELECT series_id, tick, (1.0::DOUBLE + ix::DOUBLE / 10.0) * ({_PROFILE}[(tick % 24 + 1)::INTEGER]::DOUBLE / 100.0) * (1.0::DOUBLE + 0.03::DOUBLE * z) AS y_true FROM fz),
fleet AS (SELECT series_id, tick, (tick % 24)::INTEGER AS slot, CASE WHEN NOT bad THEN y_true WHEN style = 0 THEN 0.0 WHEN style = 1 THEN y_true * 2.0 ELSE y_true * 0.5 END AS y
  FROM (SELECT *, (31 * tick * tick + 17 * tick + 7) % 10007 < 500 AS bad, ((13 * tick * tick + 5 * tick + 3) % 1009) % 3 AS style FROM f0))"""


def _vectors(source: str, by: str, scale: str = "1.0") -> str:
    return f"""SELECT {by}, median(y) AS theta, median(abs(y - t)) * {scale} AS mad, count(*) AS n
FROM (SELECT *, median(y) OVER (PARTITION BY {by}) AS t FROM {source}) GROUP BY {by}"""


_Z975 = "1.959963984540054"


def _fence(source: str, by: str, model: str) -> str:
    if model == "iqr":
        return f"""SELECT {by}, count(*) AS n, q1 - 1.5 * (q3 - q1) AS lo, q3 + 1.5 * (q3 - q1) AS hi, avg(y) AS centre FROM
 (SELECT *, quantile_cont(y, 0.25) OVER (PARTITION BY {by}) AS q1, quantile_cont(y, 0.75) OVER (PARTITION BY {by}) AS q3 FROM {source}) GROUP BY {by}, q1, q3"""
    if model == "hinge":
        halves = "list_aggregate(v[1:(n + 1) // 2], 'median') AS q1, list_aggregate(v[n - (n + 1) // 2 + 1:n], 'median') AS q3"
        return f"""SELECT {by}, n, q1 - 1.5 * (q3 - q1) AS lo, q3 + 1.5 * (q3 - q1) AS hi FROM (SELECT {by}, n, {halves} FROM
 (SELECT {by}, list_sort(list(y)) AS v, count(*) AS n FROM {source} GROUP BY {by}))"""
    scale = {"normal": "1.4826", "literal": "1.0"}[model]
    return f"SELECT {by}, n, theta - {_Z975} * mad AS lo, theta + {_Z975} * mad AS hi, theta AS centre FROM ({_vectors(source, by, scale)})"


def _gamma_flags(source: str, by: str) -> str:
    """Membership by the distribution function itself: no quantile is inverted. Series for the lower part of the
    incomplete integral; groups without a gamma take the boxplot."""
    return f"""par AS (SELECT *, (theta / mad) * (theta / mad) AS a, mad * mad / theta AS s FROM ({_vectors(source, by, '1.4826')}) WHERE theta > 0 AND mad > 0),
pts AS (SELECT DISTINCT {by}, y, a, y / s AS x FROM {source} JOIN par USING ({by})),
cdf AS (SELECT {by}, y, CASE WHEN x <= 0 THEN 0.0 WHEN x > a + 12 * sqrt(a) + 60 THEN 1.0 ELSE
  (SELECT sum(exp(a * ln(x) - x - lgamma(a + k.range + 1) + k.range * ln(x))) FROM range(1500) k) END AS f FROM pts),
flags AS (SELECT t.*, coalesce(c.f < 0.025 OR c.f > 0.975, false) AS is_outlier FROM {source} t LEFT JOIN cdf c USING ({by}, y))"""


def _gamma_quantiles(source: str, by: str) -> str:
    """(by, q, value) for rows (by, a, s) of shape and scale: the distribution function of the series above, halved
    between its ends. Null shapes give null values."""
    return f"""WITH RECURSIVE steps AS (SELECT {by}, q, a, s, 0.0::DOUBLE AS lo, a + 12 * sqrt(a) + 60 AS hi, 0 AS step FROM {source}, (VALUES (0.025::DOUBLE), (0.5::DOUBLE), (0.975::DOUBLE)) t(q)
UNION ALL SELECT {by}, q, a, s, CASE WHEN f < q THEN x ELSE lo END, CASE WHEN f < q THEN hi ELSE x END, step + 1 FROM
 (SELECT *, (SELECT sum(exp(a * ln(x) - x - lgamma(a + k.range + 1) + k.range * ln(x))) FROM range(1500) k) AS f FROM (SELECT *, (lo + hi) / 2 AS x FROM steps WHERE step < 64)))
SELECT {by}, q, round((lo + hi) / 2 * s, 6) AS value FROM steps WHERE step = 64"""


def _flags(source: str, by: str, model: str) -> str:
    return f"fence AS ({_fence(source, by, model)}), flags AS (SELECT t.*, f.lo, f.hi, f.centre, t.y < f.lo OR t.y > f.hi AS is_outlier FROM {source} t JOIN fence f USING ({by}))"


_SHOW = "SELECT tick, slot, vp_id::INTEGER AS vp_id, round(y, 6) AS y, is_polluted, is_outlier FROM flags"


def _score(name: str, flags: str = "flags") -> str:
    return f"""SELECT strategy, tp, fp, tn, fn, round((tp + tn) / (tp + fp + tn + fn), 6) AS accuracy, round(p, 6) AS precision, round(r, 6) AS recall, round(2.0 * p * r / (p + r), 6) AS f_measure FROM
 (SELECT *, tp / nullif(tp + fp, 0) AS p, tp / nullif(tp + fn, 0) AS r FROM (SELECT '{name}' AS strategy, count(*) FILTER (is_polluted AND is_outlier) AS tp,
  count(*) FILTER (NOT is_polluted AND is_outlier) AS fp, count(*) FILTER (NOT is_polluted AND NOT is_outlier) AS tn, count(*) FILTER (is_polluted AND NOT is_outlier) AS fn FROM {flags}))"""


def _scores(base: str, source: str, by: str, models: tuple[str, ...]) -> str:
    parts = []
    for m in models:
        body = _gamma_flags(source, by) if m == "gamma" else _flags(source, by, m)
        parts.append(f"SELECT * FROM (WITH {body} {_score(m)})")
    return f"WITH {base} " + " UNION ALL ".join(parts)


_M, _Y = f"WITH {_MONTH} ", f"WITH {_YEAR} "
_PAIRS = f"v AS ({_vectors('month', 'slot')}), pairs AS (SELECT a.slot AS a, b.slot AS b, sqrt((a.theta - b.theta) ** 2 + (a.mad - b.mad) ** 2) AS dist FROM v a JOIN v b ON a.slot < b.slot)"
_LINES = "lines AS (SELECT k, sum(y * cos(2 * pi() * ((k * tick) % 720) / 720.0)) AS re, -sum(y * sin(2 * pi() * ((k * tick) % 720) / 720.0)) AS im FROM month, (SELECT range AS k FROM range(361)) GROUP BY k)"
_DFT = f", {_LINES} SELECT k::INTEGER AS k, round(re, 4) + 0.0 AS re, round(im, 4) + 0.0 AS im FROM lines"
_REGIONS = "SELECT min(tick) AS first_tick, max(tick) AS last_tick FROM (SELECT tick, tick - row_number() OVER (ORDER BY tick) AS g FROM {0} WHERE {1}) GROUP BY g"

ORACLES: dict[str, str] = {
    "w_month_series": _M + "SELECT tick, round(y_true, 6) AS y_true, round(y, 6) AS y, is_polluted, style FROM month",
    "w_year_series": _Y + "SELECT tick, round(y_true, 6) AS y_true, round(y, 6) AS y, is_polluted, style FROM year",
    "w_year_mild_series": f"WITH {_year(_MILD)} SELECT tick, round(y_true, 6) AS y_true, round(y, 6) AS y, is_polluted, style FROM year",
    "w_weekly_series": f"WITH {_days('1995-01-02', 2499)}, {_z('days', 'day')} SELECT day AS tick, round({_WEEK}[(day % 7 + 1)::INTEGER]::DOUBLE / 100.0 * (1.0::DOUBLE + 0.03::DOUBLE * z) * ({_SEASON}[month(DATE '1995-01-02' + day::INTEGER)]::DOUBLE / 100.0), 10) AS y FROM z",
    "w_house_series": f"WITH {_FLEET} SELECT tick, round(y, 6) AS y FROM fleet WHERE series_id = (SELECT min(series_id) FROM fleet) AND tick BETWEEN 24 AND 551",
    "polluted_series": _M + "SELECT tick, style, round(y_true, 6) AS y_true, round(y, 6) AS y FROM month WHERE is_polluted",
    "resample_hourly": f"WITH {_HOURLY} SELECT tick, round(v, 6) AS y FROM hourly",
    "resample_variants": """WITH e AS (SELECT event_type, floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600)::BIGINT AS tick, value FROM events)
SELECT event_type, tick, round(sum(round(value * 100)::BIGINT)::DOUBLE / 100.0, 6) AS y, 'sum' AS how FROM e GROUP BY ALL
UNION ALL SELECT event_type, tick, round(avg(value), 6), 'mean' FROM e GROUP BY ALL UNION ALL SELECT event_type, tick, count(value)::DOUBLE, 'count' FROM e GROUP BY ALL
UNION ALL SELECT event_type, tick, round(value, 6), 'last' FROM (SELECT event_type, tick, value, row_number() OVER (PARTITION BY event_type, tick ORDER BY ts DESC, value DESC) AS r
 FROM (SELECT *, floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600)::BIGINT AS tick FROM events WHERE value IS NOT NULL)) WHERE r = 1""",
    "gap_fill": f"WITH {_HOURLY} SELECT tick, was_missing, round(v, 6) AS y_filled FROM filled",
    "missing_ticks": """WITH e AS (SELECT DISTINCT event_type AS series_id, floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600)::BIGINT AS tick FROM events)
SELECT s.series_id, r.range AS tick FROM (SELECT DISTINCT series_id FROM e) s CROSS JOIN range(720) r ANTI JOIN e ON e.series_id = s.series_id AND e.tick = r.range""",
    "slot_assignment": _M + "SELECT tick, slot, period_ix FROM month",
    "interval_slots": "SELECT floor((epoch(ts) % 86400) / (86400.0 / 7))::INTEGER AS slot, count(*) AS n, sum(round(value * 100)::BIGINT)::DOUBLE / 100.0 AS total FROM (SELECT date_trunc('second', ts) AS ts, value FROM events) GROUP BY 1",
    "slot_range_filter": _M + "SELECT tick, slot, round(y, 6) AS y FROM month WHERE slot BETWEEN 0 AND 9",
    "portrait_vectors": _M + f"SELECT 'all' AS series_id, slot, round(theta, 6) AS theta, round(mad, 6) AS mad, n FROM ({_vectors('month', 'slot')})",
    "portrait_vectors_one_pass": _M + f"SELECT 'all' AS series_id, slot, round(theta, 6) AS theta, round(mad, 6) AS mad, n FROM ({_vectors('month', 'slot')})",
    "portrait_vectors_mean_sd": _M + "SELECT 'all' AS series_id, slot, round(avg(y), 6) AS theta, round(stddev_samp(y), 6) AS mad, count(*) AS n FROM month GROUP BY slot",
    "landscape_vector": _M + f"SELECT series_id, round(theta, 6) AS theta, round(mad, 6) AS mad, n, 'all' AS scope FROM ({_vectors('month', 'series_id')}) UNION ALL SELECT series_id, round(theta, 6), round(mad, 6), n, 'hours 1-10' FROM ({_vectors('(SELECT * FROM month WHERE slot < 10)', 'series_id')})",
    "matrix_view": _M + "SELECT period_ix, " + ", ".join(f"round(max(y) FILTER (slot = {i}), 6) AS h{i}" for i in range(24)) + " FROM month GROUP BY 1",
    "matrix_melt": _M + "SELECT period_ix, slot, round(y, 6) AS y FROM month",
    "power_spectrum": _M + _DFT,
    "power_spectrum_fft": _M + _DFT,
    "power_spectrum_blocked": _M + _DFT,
    "window_membership": _M + "SELECT d.range AS draw, count(*) AS n, round(max(y), 6) AS most FROM month JOIN range(12) d ON tick >= d.range * 50 AND tick < d.range * 50 + 120 GROUP BY 1",
    "similarity_pairs": _M + f", {_PAIRS} SELECT a, b, round(dist, 6) AS dist FROM pairs",
    "similarity_edges": _M + f", {_PAIRS} SELECT a, b FROM pairs WHERE dist * 3.3 <= 1 + 1e-12",
    "similarity_edges_grid": _M + f", {_PAIRS} SELECT a, b FROM pairs WHERE dist * 3.3 <= 1 + 1e-12",
    "graph_degrees": _M + f", {_PAIRS} SELECT slot, count(*) AS degree FROM (SELECT unnest([a, b]) AS slot FROM pairs WHERE dist * 3.3 <= 1 + 1e-12) GROUP BY 1",
    "topk_similar_pairs": _M + f", {_PAIRS} SELECT a, b, round(dist, 6) AS dist FROM pairs ORDER BY 3, 1, 2 LIMIT 10",
    "cover_violations": "SELECT 0::BIGINT AS pairs_below, 0::BIGINT AS not_once",
    "cover_rounds_agree": "SELECT 0::BIGINT AS differences",
    "separation_fixed": _M + f", v AS ({_vectors('month', 'vp_id')}), p AS (SELECT sqrt((a.theta - b.theta) ** 2 + (a.mad - b.mad) ** 2) AS d FROM v a JOIN v b ON a.vp_id < b.vp_id) SELECT round(avg(1.0 / d), 6) AS score_literal, round(avg(d), 6) AS score_distance FROM p",
    "block_vectors": _Y + f"SELECT period_ix, round(theta, 6) AS theta, round(mad, 6) AS mad, n FROM ({_vectors('year', 'period_ix')})",
    "fences_normal": _M + f"SELECT vp_id, n, round(lo, 6) AS lo, round(hi, 6) AS hi FROM ({_fence('month', 'vp_id', 'normal')})",
    "fences_normal_literal": _M + f"SELECT vp_id, n, round(lo, 6) AS lo, round(hi, 6) AS hi FROM ({_fence('month', 'vp_id', 'literal')})",
    "fences_normal_moments": _M + f"SELECT vp_id, count(*) AS n, round(avg(y) - {_Z975} * stddev_samp(y), 6) AS lo, round(avg(y) + {_Z975} * stddev_samp(y), 6) AS hi FROM month GROUP BY 1",
    "fences_boxplot": _M + f"SELECT vp_id, n, round(lo, 6) AS lo, round(hi, 6) AS hi FROM ({_fence('month', 'vp_id', 'iqr')})",
    "small_detect_normal": _M + f", {_flags('month', 'vp_id', 'normal')} {_SHOW}",
    "small_detect_iqr": _M + f", {_flags('month', 'vp_id', 'iqr')} {_SHOW}",
    "small_detect_gamma": _M + f", {_gamma_flags('month', 'vp_id')} {_SHOW}",
    "small_scores": _scores(_MONTH, "month", "vp_id", ("normal", "iqr", "gamma")),
    "large_detect_normal": _Y + f", {_flags('year', 'vld_id, vp_id', 'normal')} {_SHOW}",
    "large_detect_iqr": _Y + f", {_flags('year', 'vld_id, vp_id', 'iqr')} {_SHOW}",
    "flagged_points": _M + f", {_flags('month', 'vp_id', 'iqr')} SELECT tick, slot, round(y, 6) AS y, round(lo, 6) AS lo, round(hi, 6) AS hi FROM flags WHERE is_outlier",
    "polluted_regions": _Y + _REGIONS.format("year", "is_polluted"),
    "strategy_overlap": _M + f", n AS (WITH {_flags('month', 'vp_id', 'normal')} SELECT tick FROM flags WHERE is_outlier), i AS (WITH {_flags('month', 'vp_id', 'iqr')} SELECT tick FROM flags WHERE is_outlier) SELECT tick FROM n INTERSECT SELECT tick FROM i",
    "strategy_difference": _M + f", n AS (WITH {_flags('month', 'vp_id', 'normal')} SELECT tick FROM flags WHERE is_outlier), i AS (WITH {_flags('month', 'vp_id', 'iqr')} SELECT tick FROM flags WHERE is_outlier) SELECT tick FROM n EXCEPT SELECT tick FROM i",
    "impute_missing": f"WITH {_HOURLY}, s AS (SELECT tick, was_missing, tick % 24 AS slot, CASE WHEN NOT was_missing THEN v END AS y FROM filled), m AS (SELECT slot, median(y) AS theta FROM s GROUP BY 1) SELECT tick, was_missing, round(coalesce(y, theta), 6) AS y_clean FROM s JOIN m USING (slot)",
    "replaced_values": _M + f", {_flags('month', 'vp_id', 'iqr')} SELECT tick, round(y, 6) AS y, round(centre, 6) AS y_clean FROM flags WHERE is_outlier",
    "imputation_error": _M + f", {_flags('month', 'vp_id', 'iqr')} SELECT round(avg(abs(CASE WHEN is_outlier THEN centre ELSE y END - y_true)), 6) AS mae_clean, round(avg(abs(y - y_true)), 6) AS mae_polluted FROM flags WHERE is_polluted",
    "severity_classes": _M + """, q AS (SELECT *, quantile_cont(y, 0.25) OVER (PARTITION BY vp_id) AS q1, quantile_cont(y, 0.75) OVER (PARTITION BY vp_id) AS q3 FROM month),
a AS (SELECT vp_id, greatest(q1 - y, y - q3) AS away, q3 - q1 AS span FROM q) SELECT vp_id, CASE WHEN away > 3.0 * span THEN 'extreme' WHEN away > 1.5 * span THEN 'mild' ELSE 'none' END AS severity, count(*) AS n FROM a GROUP BY ALL""",
    "label_scores": f"WITH docs AS (SELECT d.doc_id, lang, n_chars::DOUBLE AS y, quality = 0 AS is_polluted FROM documents d JOIN labels l ON l.doc_id = d.doc_id), {_flags('docs', 'lang', 'iqr')} {_score('length by language')}",
    "fleet_vectors": f"WITH {_FLEET} SELECT series_id, slot, round(theta, 6) AS theta, round(mad, 6) AS mad, n FROM ({_vectors('fleet', 'series_id, slot')})",
    "quartiles": _M + "SELECT slot, round(quantile_cont(y, 0.25), 6) AS q1, round(quantile_cont(y, 0.5), 6) AS q2, round(quantile_cont(y, 0.75), 6) AS q3 FROM month GROUP BY 1",
    "distinct_users_hourly": "SELECT hour(ts)::INTEGER AS hour, count(DISTINCT user_id) AS users FROM events GROUP BY 1",
    "load_rollup": """SELECT r_name, n_name, sum(round(l_quantity::DOUBLE * 100)::BIGINT)::DOUBLE / 100.0 AS load, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey
JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)""",
    "load_cube": "SELECT event_type, hour, sum(round(value * 100)::BIGINT)::DOUBLE / 100.0 AS load FROM (SELECT *, hour(ts)::INTEGER AS hour FROM events) GROUP BY CUBE (event_type, hour)",
    "top_deviation": _M + """SELECT slot, place, tick, away FROM (SELECT slot, tick, away, row_number() OVER (PARTITION BY slot ORDER BY away DESC, tick) AS place FROM
(SELECT slot, tick, round(abs(y - median(y) OVER (PARTITION BY slot)), 6) AS away FROM month)) WHERE place <= 2""",
    "rolling_slot_mean": _M + "SELECT tick, round(avg(y) OVER (PARTITION BY slot ORDER BY period_ix ROWS BETWEEN 6 PRECEDING AND CURRENT ROW), 6) AS mean7 FROM month",
    "asof_fences": "SELECT r.range AS tick, CASE WHEN r.range >= 7 THEN least(5, (r.range - 7) // 120) END AS in_force FROM range(720) r",
    "calendar_slots": "SELECT (dayofweek(o_orderdate) + 1)::INTEGER AS weekday, quarter(o_orderdate)::INTEGER AS season, count(*) AS n FROM orders GROUP BY 1, 2",
    "series_key": "SELECT event_type || ':' || lpad(user_id::VARCHAR, 6, '0') AS series_key, count(*) AS n FROM events GROUP BY 1",
    "props_slot": "SELECT json_extract_string(props, '$.k')::INTEGER AS k, count(*) AS n FROM events GROUP BY 1",
    "curve_array": _M + "SELECT period_ix, round(max(y), 6) AS peak, round(sum(y), 6) AS total FROM month GROUP BY 1",
    "sql_detect": _M + "SELECT tick, round(y - t, 6) AS away FROM (SELECT *, median(y) OVER (PARTITION BY slot) AS t FROM month) WHERE abs(y - t) > 0.5",
    "udtf_period_ticks": """WITH h AS (SELECT DISTINCT event_type, floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600)::BIGINT AS tick FROM events WHERE ts IS NOT NULL),
d AS (SELECT event_type, floor(min(tick) / 24)::BIGINT AS first, floor(max(tick) / 24)::BIGINT AS last FROM h GROUP BY 1),
g AS (SELECT event_type, unnest(range(first * 24, (last + 1) * 24)) AS tick FROM d)
SELECT g.event_type, (((g.tick % 24) + 24) % 24)::INTEGER AS slot, count(*) AS n, count(h.tick) AS n_held FROM g LEFT JOIN h ON g.event_type IS NOT DISTINCT FROM h.event_type AND g.tick = h.tick GROUP BY 1, 2""",
    "asked_quantiles": f"""WITH m AS (SELECT event_type, avg(value) AS c, stddev_samp(value) AS d FROM events WHERE value IS NOT NULL GROUP BY 1),
par AS (SELECT event_type, CASE WHEN c > 0 AND d > 0 THEN (c / d) * (c / d) END AS a, CASE WHEN c > 0 AND d > 0 THEN d * d / c END AS s FROM m) SELECT * FROM ({_gamma_quantiles('par', 'event_type')})""",
    "validate_events": f"WITH {_HOURLY} SELECT 0::BIGINT AS null_ticks, 0::BIGINT AS repeated_ticks, count(*) FILTER (v < 0) AS negative_values, 0::BIGINT AS not_finite_values FROM hourly",
    "gap_default_compare": f"""WITH {_HOURLY}, b AS (SELECT tick % 24 AS slot, was_missing, kind, CASE WHEN NOT was_missing THEN v WHEN kind = 'zero' THEN 0.0 ELSE 1e12 END AS y FROM filled, (VALUES ('zero'), ('sentinel')) k(kind)),
q AS (SELECT *, quantile_cont(y, 0.25) OVER (PARTITION BY kind, slot) AS q1, quantile_cont(y, 0.75) OVER (PARTITION BY kind, slot) AS q3 FROM b)
SELECT count(*) FILTER (was_missing) AS missing, count(*) FILTER (was_missing AND (y < q1 - 1.5 * (q3 - q1) OR y > q3 + 1.5 * (q3 - q1))) AS flagged, kind AS gap_default FROM q GROUP BY kind""",
    "portrait_spans": _M + """, v AS (SELECT slot, round(median(y), 6) AS p FROM month GROUP BY 1), s AS (SELECT slot, CASE WHEN p < 1.0 THEN 0 WHEN p < 1.4 THEN 1 WHEN p < 1.7 THEN 2 ELSE 3 END AS vp_id FROM v),
r AS (SELECT vp_id, slot - row_number() OVER (PARTITION BY vp_id ORDER BY slot) AS g FROM s) SELECT vp_id::INTEGER AS vp_id, count(*)::DOUBLE AS span, count(DISTINCT g) AS n_intervals FROM r GROUP BY 1""",
    "portrait_vectors_approx": _M + "SELECT 'all' AS series_id, slot, theta, quantile_disc(abs(y - theta), 0.5) AS mad, count(*) AS n FROM (SELECT slot, y, quantile_disc(y, 0.5) OVER (PARTITION BY slot) AS theta FROM month) GROUP BY slot, theta",
    "harmonic_series": _M + f", {_LINES} SELECT 'all' AS series_id, (k // 30)::INTEGER AS harmonic, round(CASE WHEN k = 0 THEN re / 720 ELSE 2.0 * sqrt(re * re + im * im) / 720 END, 6) AS amplitude, round(CASE WHEN k = 0 THEN 0.0 ELSE atan2(im, re) END, 6) AS phase FROM lines WHERE k % 30 = 0 AND k <= 150",
    # Planted answers.
    "fundamental_period": "SELECT * FROM (VALUES ('month', 24.0::DOUBLE), ('year', 24.0::DOUBLE), ('raw', NULL::DOUBLE), ('weekly', 7.0::DOUBLE)) t(fixture, period_ticks)",
    "negative_control": "SELECT NULL::DOUBLE AS period_ticks",
    "fleet_periods": "SELECT DISTINCT event_type AS series_id, 24.0::DOUBLE AS period_ticks FROM events",
    "periodic_series_only": "SELECT DISTINCT event_type AS series_id, 720::BIGINT AS n FROM events",
    "spectrum_peaks": _M + f", {_LINES}, p AS (SELECT k, round(re * re + im * im, 4) AS power FROM lines) SELECT k::INTEGER AS k FROM (SELECT *, lag(power, 1, -1.0) OVER (ORDER BY k) AS b, lead(power, 1, -1.0) OVER (ORDER BY k) AS a FROM p) WHERE power > b AND power > a AND power > 100",
    # Counts that are zero where the method holds.
    "cover_exact_violations": "SELECT 0::BIGINT AS pairs_below, 0::BIGINT AS not_once",
    "cover_rounds_path": "SELECT 0::BIGINT AS not_once, 0::BIGINT AS not_cliques",
    "landscape_cover_violations": "SELECT 0::BIGINT AS pairs_below, 0::BIGINT AS not_once",
    "landscape_portrait_violations": "SELECT 0::BIGINT AS pairs_below, 0::BIGINT AS not_once",
    "learned_map_agrees": "SELECT 0::BIGINT AS differences",
    "learned_small_consistent": "SELECT 0::BIGINT AS flags_differ, 0::BIGINT AS ticks_lost, 0::BIGINT AS without_group",
    "learned_large_consistent": "SELECT 0::BIGINT AS flags_differ, 0::BIGINT AS ticks_lost, 0::BIGINT AS without_group",
    "smoother_dense_agrees": "SELECT 0::BIGINT AS differ",
    "stationarity_route": " UNION ALL ".join(
        f"""SELECT * FROM (WITH {base}, b AS (SELECT median(y) AS t FROM {name} GROUP BY period_ix), m AS (SELECT median(t) AS c FROM b), d AS (SELECT median(abs(t - c)) AS w FROM b, m)
SELECT '{name}' AS fixture, round(w / nullif(c, 0.0), 6) AS level_spread, CASE WHEN w <= 0.25 * abs(c) THEN 'stationary' ELSE 'nonstationary' END AS route FROM m, d)"""
        for name, base in (("month", _MONTH), ("year", _YEAR))
    ),
    "fences_boxplot_hinge": _M + f"SELECT vp_id, n, round(lo, 6) AS lo, round(hi, 6) AS hi FROM ({_fence('month', 'vp_id', 'hinge')})",
    "fences_gamma_centres": _M + f"SELECT vp_id, round(theta, 6) AS mean, round((theta / mad) * (theta / mad) / (mad * mad / theta), 3) AS ratio FROM ({_vectors('month', 'vp_id', '1.4826')})",
    "fences_auto": _Y + f""", a AS ({_fence('year', 'vld_id, slot', 'normal')}), b AS ({_fence('year', 'vld_id, slot', 'iqr')})
SELECT vld_id::INTEGER AS vld_id, slot, a.n, round(CASE WHEN a.n < 30 THEN b.lo ELSE a.lo END, 6) AS lo, round(CASE WHEN a.n < 30 THEN b.hi ELSE a.hi END, 6) AS hi, CASE WHEN a.n < 30 THEN 'iqr:small' ELSE 'normal' END AS model FROM a JOIN b USING (vld_id, slot)""",
    "own_strategy": _M + f", flags AS (SELECT *, y < lo OR y > hi AS is_outlier FROM (SELECT *, quantile_cont(y, 0.05) OVER (PARTITION BY vp_id) AS lo, quantile_cont(y, 0.95) OVER (PARTITION BY vp_id) AS hi FROM month)) {_SHOW}",
    "fence_params": _M + f", a AS ({_fence('month', 'vp_id', 'iqr')}), b AS ({_fence('month', 'vp_id', 'normal')}) SELECT vp_id, 2::INTEGER AS models, round(a.lo, 6) AS iqr_lo, round(b.hi, 6) AS normal_hi FROM a JOIN b USING (vp_id)",
    "join_fences_broadcast": _M + f", {_flags('month', 'vp_id', 'iqr')} {_SHOW}",
    "join_sort_merge": _M + f", {_flags('month', 'vp_id', 'iqr')} {_SHOW}",
    "large_detect_gamma": _Y + f", {_gamma_flags('year', 'vld_id, vp_id')} {_SHOW}",
    "large_scores": _scores(_YEAR, "year", "vld_id, vp_id", ("normal", "iqr", "gamma")),
    "ablation_fixed": " UNION ALL ".join(
        f"SELECT * FROM (WITH {base}, {_flags(name, by, model)} {_score(title)})"
        for base, name, by, model, title in (
            (_MONTH, "month", "series_id", "iqr", "one group"),
            (_MONTH, "month", "slot", "iqr", "basic portraits"),
            (_MONTH, "month", "vp_id", "literal", "normal unscaled"),
            (_YEAR, "year", "vp_id", "iqr", "year without landscapes"),
        )
    ),
    "macro_scores": _M + f""", {_flags('month', 'vp_id', 'iqr')}, c AS (SELECT vp_id, count(*) FILTER (is_polluted AND is_outlier) AS tp, count(*) FILTER (NOT is_polluted AND is_outlier) AS fp,
 count(*) FILTER (NOT is_polluted AND NOT is_outlier) AS tn, count(*) FILTER (is_polluted AND NOT is_outlier) AS fn FROM flags GROUP BY vp_id),
r AS (SELECT (tp + tn) / (tp + fp + tn + fn) AS a, tp / nullif(tp + fp, 0) AS p, tp / nullif(tp + fn, 0) AS r FROM c)
SELECT round(avg(a), 6) AS accuracy, round(avg(p), 6) AS precision, round(avg(r), 6) AS recall, round(avg(2.0 * p * r / nullif(p + r, 0)), 6) AS f_measure, count(*) AS groups FROM r""",
    "region_scores": _M + f""", {_flags('month', 'vp_id', 'iqr')}, a AS ({_REGIONS.format('flags', 'is_polluted')}), b AS ({_REGIONS.format('flags', 'is_outlier')}),
n AS (SELECT (SELECT count(*) FROM a) AS labelled, (SELECT count(*) FROM b) AS detected, (SELECT count(*) FROM a WHERE EXISTS (SELECT 1 FROM b WHERE a.first_tick <= b.last_tick AND b.first_tick <= a.last_tick)) AS found,
 (SELECT count(*) FROM b WHERE EXISTS (SELECT 1 FROM a WHERE a.first_tick <= b.last_tick AND b.first_tick <= a.last_tick)) AS "right")
SELECT labelled, detected, found, "right", round("right" / detected, 6) AS precision, round(found / labelled, 6) AS recall, round(2.0 * ("right" / detected) * (found / labelled) / ("right" / detected + found / labelled), 6) AS f_measure FROM n""",
    "review_loop": _M + f", {_flags('month', 'vp_id', 'iqr')} SELECT CASE WHEN tick % 2 = 0 THEN 'replace' WHEN tick >= 100 AND tick < 300 THEN 'keep' ELSE 'pending' END AS verdict, count(*) AS n FROM flags WHERE is_outlier GROUP BY 1",
    "replaced_median": _M + f", {_flags('month', 'vp_id', 'iqr')} SELECT tick, round(m, 6) AS y_clean FROM (SELECT *, median(y) OVER (PARTITION BY vp_id) AS m FROM flags) WHERE is_outlier",
    "cleanse_defaults": f"""WITH {_HOURLY}, q AS (SELECT tick, was_missing, v AS y, quantile_cont(v, 0.25) OVER (PARTITION BY tick % 24) AS q1, quantile_cont(v, 0.75) OVER (PARTITION BY tick % 24) AS q3, avg(v) OVER (PARTITION BY tick % 24) AS c FROM filled),
f AS (SELECT *, y < q1 - 1.5 * (q3 - q1) OR y > q3 + 1.5 * (q3 - q1) AS is_outlier FROM q) SELECT tick, was_missing, is_outlier, round(CASE WHEN is_outlier THEN c ELSE y END, 6) AS y_clean FROM f""",
    "peak_rank": _M + f""", v AS (SELECT slot, round(theta, 6) AS top FROM ({_vectors('month', 'slot')})) SELECT slot, rank() OVER w AS place, dense_rank() OVER w AS dense_place, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 6) AS share_before
FROM v WINDOW w AS (ORDER BY top DESC, slot)""",
    "sampled_vectors": _M + f", s AS (SELECT * FROM month WHERE (tick * 7919 + 13) % 1000 < 300) SELECT slot, n, round(theta, 6) AS theta, round(mad, 6) AS mad FROM ({_vectors('s', 'slot')})",
    "observed_counts": _M + "SELECT count(*) AS n, count(*) FILTER (is_polluted) AS polluted, max(tick) AS last FROM month",
    "udf_gamma_fence": _M + f""", par AS (SELECT slot, CASE WHEN theta > 0 AND mad > 0 THEN (theta / mad) * (theta / mad) END AS a, CASE WHEN theta > 0 AND mad > 0 THEN mad * mad / theta END AS s
FROM ({_vectors('month', 'slot', '1.4826')})) SELECT * FROM ({_gamma_quantiles('par', 'slot')})""",
}
