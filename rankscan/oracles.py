"""DuckDB SQL for the queries of ``workloads.py`` that SQL can express."""

from __future__ import annotations


def _with(*parts: str, last: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n" + last


def _filled(name: str, counts: str, lo: int, hi: int) -> str:
    return f"""{name}_c AS ({counts}),
{name} AS (SELECT g.series_id, g.t::bigint AS t, coalesce(c.value, 0)::double AS value
  FROM (SELECT series_id, unnest(range({lo}, {hi} + 1)) AS t FROM (SELECT DISTINCT series_id FROM {name}_c)) g LEFT JOIN {name}_c c ON c.series_id = g.series_id AND c.t = g.t)"""


ORDERS = _filled("s", "SELECT o_orderpriority AS series_id, date_diff('day', DATE '1995-01-01', o_orderdate::date) + 1 AS t, count(*) AS value FROM orders GROUP BY 1, 2", 1, 2405)
SHIP = _filled("s", "SELECT l_returnflag || l_linestatus AS series_id, date_diff('day', DATE '1995-01-02', l_shipdate::date) + 1 AS t, count(*) AS value FROM lineitem GROUP BY 1, 2", 1, 2499)
HOURLY = _filled("s", "SELECT event_type AS series_id, (epoch_us(ts) - 1704067200000000) // 3600000000 + 1 AS t, count(*) AS value FROM events GROUP BY 1, 2", 1, 720)
POINTS = _filled("s", "SELECT event_type AS series_id, ((epoch_us(ts) - lo) * 720) // (hi - lo + 1) + 1 AS t, count(*) AS value FROM events, (SELECT min(epoch_us(ts)) AS lo, max(epoch_us(ts)) AS hi FROM events) GROUP BY 1, 2", 1, 720)
WEEKLY = _filled("s", "SELECT l_suppkey::varchar AS series_id, date_diff('day', DATE '1995-01-02', l_shipdate::date) // 7 + 1 AS t, sum(floor(l_extendedprice * (1 - l_discount) * 100 + 0.5)::bigint)::double AS value FROM lineitem GROUP BY 1, 2", 1, 357)
THOUSANDS = WEEKLY + ",\nk AS (SELECT series_id, t, value / 100000 AS value FROM s)"
VECTORS = "s AS (SELECT vec_id::varchar AS series_id, unnest(range(1, len(embedding) + 1))::bigint AS t, unnest(embedding)::double AS value FROM embeddings)"


def _ordered(table: str, key: str, order: str, value: str) -> str:
    return f"s AS (SELECT {key} AS series_id, row_number() OVER (PARTITION BY {key} ORDER BY {order}) AS t, ({value})::double AS value FROM {table})"


USERS = _ordered("events", "user_id::varchar", "ts, event_id", "value")
TURNS = _ordered("conversations", "conv_id::varchar", "turn", "length(text)")
DOCS = _ordered("documents", "lang", "doc_id", "n_chars")
LABELS = _ordered("labels", "'quality'", "doc_id", "quality")
PAGES = _ordered("pages", "'pages'", "page_id", "length(html)")
PARTS = "s AS (SELECT 'part' AS series_id, (p_partkey - (SELECT min(p_partkey) FROM part) + 1)::bigint AS t, p_retailprice AS value FROM part)"
ALL = "SELECT series_id, t, value FROM s"

RANKED = "r AS (SELECT series_id, t, value, row_number() OVER (PARTITION BY series_id ORDER BY value, md5(series_id || '|' || t::varchar || '|42'), t) AS r FROM s)"


def _windows(w_max: int, w_min: int = 1) -> str:
    return f"""c AS (SELECT series_id, t, sum(r) OVER (PARTITION BY series_id ORDER BY t)::bigint AS c, count(*) OVER (PARTITION BY series_id) AS n FROM r),
c0 AS (SELECT series_id, t, c FROM c UNION ALL SELECT DISTINCT series_id, 0, 0 FROM c),
win AS (SELECT c.series_id, (c.t - w + 1)::integer AS s, w::integer AS w, c.n, (c.c - c0.c)::bigint AS q
  FROM c, range({w_min}, {w_max} + 1) x(w) JOIN c0 ON c0.series_id = c.series_id AND c0.t = c.t - w WHERE c.t >= w)"""


def _law(n: int, w_max: int) -> str:
    return f"""dp(i, w, phi, ways) AS (SELECT 0, 0, 0, 1::hugeint UNION ALL
  SELECT i + 1, w + k, phi + k * (i + 1), sum(ways)::hugeint FROM dp, (VALUES (0), (1)) x(k) WHERE i < {n} AND w + k <= {w_max} GROUP BY ALL),
law AS (SELECT w, phi, ways, ways / sum(ways) OVER (PARTITION BY w) AS mass, sum(ways) OVER (PARTITION BY w ORDER BY phi) / sum(ways) OVER (PARTITION BY w) AS lower,
  sum(ways) OVER (PARTITION BY w ORDER BY phi DESC) / sum(ways) OVER (PARTITION BY w) AS upper FROM dp WHERE i = {n} AND w > 0)"""


def _surface(n: int, w_max: int, score: str = "least(lower, upper)") -> str:
    return f"""{RANKED},
{_windows(w_max)},
{_law(n, w_max)},
surf AS (SELECT series_id, s, win.w, q, round(log10({score}), 6) AS log10_p FROM win JOIN law ON law.w = win.w AND law.phi = win.q)"""


V_SURF = f"{VECTORS},\n{_surface(64, 8)}"
BEST = "best AS (SELECT * EXCLUDE (k) FROM (SELECT *, row_number() OVER (PARTITION BY series_id ORDER BY log10_p, s, w) AS k FROM surf) WHERE k = 1)"
BEST_RANKED = BEST + ",\nranked AS (SELECT *, row_number() OVER (ORDER BY log10_p, series_id, s, w) AS global_rank FROM best)"
MINIMA = """near AS (SELECT series_id, s + a AS s, w + b AS w, min(log10_p) AS least FROM surf, (VALUES (-1), (0), (1)) x(a), (VALUES (-1), (0), (1)) y(b) WHERE a <> 0 OR b <> 0 GROUP BY ALL),
minima AS (SELECT surf.* FROM surf LEFT JOIN near USING (series_id, s, w) WHERE least IS NULL OR log10_p <= least)"""

SQL: dict[str, str] = {}


def _put(name: str, *parts: str, last: str) -> None:
    SQL[name] = _with(*parts, last=last)


for _name, _part in {
    "bin_orders_daily": ORDERS, "bin_ship_daily": SHIP, "bin_events_hourly": HOURLY, "bin_event_points": POINTS, "supplier_weekly_series": WEEKLY, "user_value_index": USERS, "vector_series_long": VECTORS,
    "turn_length_series": TURNS, "doc_length_series": DOCS, "label_bit_series": LABELS, "page_length_series": PAGES, "part_price_series": PARTS,
}.items():
    _put(_name, _part, last=ALL)

_LINE = "l AS (SELECT series_id, regr_slope(value, t) AS a, regr_intercept(value, t) AS b FROM {x} GROUP BY 1)"
_put("detrend_supplier_weekly", THOUSANDS, _LINE.format(x="k"), last="SELECT series_id, t, round(value - (a * t + b), 3) AS value FROM k JOIN l USING (series_id)")
_put("detrend_part_price", PARTS, _LINE.format(x="s"), last="SELECT series_id, t, round(value - (a * t + b), 4) AS value FROM s JOIN l USING (series_id)")
_put("detrend_moving_median", HOURLY, last="SELECT series_id, t, value - median(value) OVER (PARTITION BY series_id ORDER BY t ROWS BETWEEN 7 PRECEDING AND 7 FOLLOWING) AS value FROM s")
_put("detrend_difference", SHIP, last="SELECT * FROM (SELECT series_id, t, value - lag(value) OVER (PARTITION BY series_id ORDER BY t) AS value FROM s) WHERE value IS NOT NULL")
_DAYS = """d AS (SELECT user_id::varchar AS series_id, date_diff('day', DATE '2024-01-01', ts::date) + 1 AS t, {how}(floor(value))::double AS value FROM events GROUP BY 1, 2),
g AS (SELECT g.series_id, g.t::bigint AS t, d.value FROM (SELECT series_id, unnest(range(1, 31)) AS t FROM (SELECT DISTINCT series_id FROM d)) g LEFT JOIN d ON d.series_id = g.series_id AND d.t = g.t)"""
_put("fill_previous_users", _DAYS.format(how="sum"), last="SELECT series_id, t, last_value(value IGNORE NULLS) OVER (PARTITION BY series_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS value FROM g")
_put(
    "fill_interpolate_users", _DAYS.format(how="max"),
    """p AS (SELECT *, last_value(value IGNORE NULLS) OVER a AS v0, last_value(CASE WHEN value IS NOT NULL THEN t END IGNORE NULLS) OVER a AS t0, first_value(value IGNORE NULLS) OVER b AS v1, first_value(CASE WHEN value IS NOT NULL THEN t END IGNORE NULLS) OVER b AS t1
  FROM g WINDOW a AS (PARTITION BY series_id ORDER BY t ROWS UNBOUNDED PRECEDING), b AS (PARTITION BY series_id ORDER BY t ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))""",
    last="SELECT series_id, t, round(coalesce(value, v0 + (v1 - v0) * (t - t0) / (t1 - t0), v0, v1), 6) AS value FROM p",
)

_put(
    "segment_ship_daily", SHIP, "seg AS (SELECT * FROM (VALUES (0, 1), (1, 901), (2, 1500)) x(seg_id, seg_start))",
    last="SELECT series_id, seg_id, seg_start::bigint AS seg_start, count(*)::integer AS n, sum(value) AS total, max(t) AS last_t FROM s JOIN seg ON t >= seg_start AND t < seg_start + 1000 GROUP BY 1, 2, 3",
)
SQL["segment_last_anchor"] = """
SELECT length, seg_id::integer AS seg_id, CASE WHEN length <= 1000 THEN 1 ELSE least(1 + seg_id * 900, length - 999) END::bigint AS seg_start
FROM (SELECT length, unnest(range(0, CASE WHEN length <= 1000 THEN 1 ELSE ceil((length - 1000) / 900)::bigint + 1 END)) AS seg_id FROM range(900, 3000, 37) x(length))
"""

_put("rank_events_hourly", HOURLY, RANKED, last="SELECT series_id, t, value, r FROM r")
_put("rank_vectors", VECTORS, RANKED, last="SELECT series_id, t, r FROM r")
_put("rank_ties_label_bits", LABELS, RANKED, last="SELECT series_id, t, value, r FROM r")
_put("rank_average_ties", HOURLY, last="SELECT series_id, t, value, rank() OVER (PARTITION BY series_id ORDER BY value) + (count(*) OVER (PARTITION BY series_id, value) - 1) / 2 AS r FROM s")
_put("rank_ordinal_ties", HOURLY, last="SELECT series_id, t, value, row_number() OVER (PARTITION BY series_id ORDER BY value, t) AS r FROM s")
_put("prefix_sums_vectors", VECTORS, RANKED, last="SELECT series_id, t, sum(r) OVER (PARTITION BY series_id ORDER BY t)::bigint AS c FROM r")
_put("rank_sums_fixed_w", VECTORS, RANKED, last="SELECT * FROM (SELECT series_id, t::integer AS s, CASE WHEN count(*) OVER f = 5 THEN sum(r) OVER f END::bigint AS q FROM r WINDOW f AS (PARTITION BY series_id ORDER BY t ROWS BETWEEN CURRENT ROW AND 4 FOLLOWING)) WHERE q IS NOT NULL")

SQL["law_enumerated_n10"] = "SELECT 10 AS n, bit_count(m)::integer AS w, list_sum([i FOR i IN range(1, 11) IF (m >> (i - 1)) & 1 = 1])::bigint AS phi, count(*) AS ways FROM range(1, 1024) x(m) GROUP BY 1, 2, 3"
for _name in ("law_recurrence_n30_w8", "law_product_n30_w8", "law_steps_n30_w8", "law_source_n30_w8"):
    _put(_name, _law(30, 8), last="SELECT 30 AS n, w::integer AS w, phi::bigint AS phi, ways::bigint AS ways FROM law")
_put("law_udtf_n30_w8", _law(30, 8), last="SELECT 30 AS n, w::integer AS w, phi::bigint AS phi, ways::bigint AS ways FROM law WHERE w = 8")
_CONDITIONED = "SELECT 50 AS n, w::integer AS w, phi::bigint AS phi, round(log10(mass), 6) + 0.0 AS log10_mass, round(log10(lower), 6) + 0.0 AS log10_lower, round(log10(upper), 6) + 0.0 AS log10_upper FROM law WHERE w IN (3, 10, 20)"
_put("law_stored_n50", _law(50, 20), last=_CONDITIONED)


def _blocks(n: int, end: str = "") -> str:
    """Event values by blocks of n consecutive ids."""
    return f"""s{end} AS (SELECT 'e' || event_id // {n} AS series_id, event_id // {n} AS k, row_number() OVER (PARTITION BY event_id // {n} ORDER BY event_id, value) AS t, value
  FROM events WHERE event_id IS NOT NULL AND value IS NOT NULL AND NOT isnan(value))"""


def _seen(n: int, widths: str, end: str = "") -> str:
    """Windows of the series of n points by rank sum."""
    return f"""{RANKED.replace("r AS", f"r{end} AS", 1).replace("FROM s)", f"FROM s{end})")},
run{end} AS (SELECT series_id, t, sum(r) OVER (PARTITION BY series_id ORDER BY t)::bigint AS c, count(*) OVER (PARTITION BY series_id) AS n FROM r{end}),
seen{end} AS (SELECT {n} AS n, w, q AS phi, count(*) AS windows FROM (SELECT t, w, n, c - lag(c, w::integer, 0) OVER (PARTITION BY series_id, w ORDER BY t) AS q FROM run{end}, {widths} x(w)) WHERE n = {n} AND t >= w GROUP BY w, q)"""


_put(
    "law_conditioning_n50_w3_10_20", _law(50, 20), _blocks(50), _seen(50, "(VALUES (3), (10), (20))"), f"told AS ({_CONDITIONED})",
    last="SELECT told.*, coalesce(windows, 0) AS windows FROM told LEFT JOIN seen USING (w, phi)",
)
_put("law_tails_n30", _law(30, 8), last="SELECT 30 AS n, w::integer AS w, phi::bigint AS phi, round(mass, 10) AS mass, round(lower, 10) AS lower, round(upper, 10) AS upper, round(least(lower, upper), 10) AS tail, round(least(1, 2 * least(lower, upper)), 10) AS two_sided FROM law")
_CRITICAL = "SELECT 64 AS n, w::integer AS w, max(phi) FILTER (lower <= {a})::bigint AS q_low, min(phi) FILTER (upper <= {a})::bigint AS q_high FROM law GROUP BY w"
_put(
    "law_critical_sums_n64", _law(64, 8), VECTORS, _seen(64, "range(1, 9)"), f"b AS ({_CRITICAL.format(a='1e-4')})",
    last="SELECT b.n, b.w, q_low, q_high, coalesce(sum(windows), 0)::bigint AS windows, coalesce(sum(windows) FILTER (phi <= q_low), 0)::bigint AS low, coalesce(sum(windows) FILTER (phi >= q_high), 0)::bigint AS high FROM b LEFT JOIN seen ON seen.w = b.w GROUP BY ALL",
)
SQL["law_convergence"] = _with(
    *(f"dp{n}(i, w, phi, ways) AS (SELECT 0, 0, 0, 1::hugeint UNION ALL SELECT i + 1, w + k, phi + k * (i + 1), sum(ways)::hugeint FROM dp{n}, (VALUES (0), (1)) x(k) WHERE i < {n} AND w + k <= 10 GROUP BY ALL)" for n in (50, 100, 250, 500)),
    "a AS (" + " UNION ALL ".join(f"SELECT {n} AS n, w, phi, ways FROM dp{n} WHERE i = {n} AND w IN (3, 10)" for n in (50, 100, 250, 500)) + ")",
    "told AS (SELECT n, w::integer AS w, w * (n + 1) / 2 AS mean, w * (n - w) * (n + 1) / 12 AS variance, round(sum(ways) FILTER ((phi - w * (n + 1) / 2) ^ 2 <= w * (n - w) * (n + 1) / 12) / sum(ways), 8) AS within_one FROM a GROUP BY n, w)",
    *(_blocks(n, str(n)) for n in (50, 100, 250, 500)),
    *(_seen(n, "(VALUES (3), (10))", str(n)) for n in (50, 100, 250, 500)),
    "seen AS (" + " UNION ALL ".join(f"SELECT * FROM seen{n}" for n in (50, 100, 250, 500)) + ")",
    last="SELECT told.*, coalesce(sum(windows), 0)::bigint AS windows, coalesce(sum(windows) FILTER ((phi - mean) * (phi - mean) <= variance), 0)::bigint AS windows_within FROM told LEFT JOIN seen ON seen.n = told.n AND seen.w = told.w GROUP BY ALL",
)
SQL["min_width_table"] = """
WITH b AS (SELECT n, w, (SELECT sum(log10((n - i + 1) / i)) FROM range(1, w + 1) x(i)) AS binom FROM (VALUES (50), (64), (100), (357), (500), (720), (1000)) x(n), range(1, 26) y(w) WHERE w <= n // 2)
SELECT n::integer AS n, a::integer AS minus_log10_alpha, min(w)::integer AS w FROM b, (VALUES (4), (6), (8)) z(a) WHERE -binom <= -a GROUP BY 1, 2
"""
SQL["memo_cells_table"] = "SELECT n::integer AS n, w::integer AS w_max, w::bigint * n * (n * w - w * (w - 1) // 2) AS cells FROM (VALUES (30, 8), (50, 20), (500, 50), (1000, 100)) x(n, w)"
_HASHED = """draw AS (SELECT d, i, row_number() OVER o AS w, sum(i) OVER (PARTITION BY d ORDER BY md5('42|' || d::varchar || '|' || i::varchar), i)::bigint AS phi FROM range(2000) x(d), range(1, 31) y(i) WINDOW o AS (PARTITION BY d ORDER BY md5('42|' || d::varchar || '|' || i::varchar), i)),
mc AS (SELECT 30 AS n, w::integer AS w, phi, count(*) AS hits FROM draw WHERE w <= 5 GROUP BY 1, 2, 3)"""
_put("mc_hash_law_n30", _HASHED, last="SELECT n, w, phi, hits, round(1 / sqrt(hits), 9) AS error FROM mc")
SQL["mc_required_samples"] = "SELECT a::double AS alpha, e::double AS epsilon, ceil(round(1 / (a::double * e::double * e::double), 6))::bigint AS samples FROM (VALUES (1e-2), (1e-3), (1e-4)) x(a), (VALUES (0.05), (0.1), (0.2)) y(e)"
_put("mc_error_vs_exact", _HASHED, _law(30, 5), last="SELECT 30 AS n, law.w::integer AS w, law.phi::bigint AS phi, hits IS NULL AS censored, round(coalesce(hits, 0) / 2000 / mass - 1, 9) AS error FROM law LEFT JOIN mc ON mc.w = law.w AND mc.phi = law.phi WHERE mass >= 0.01")
_put(
    "mc_decision_flips", _HASHED, _law(30, 5),
    "t AS (SELECT w, phi, least(sum(hits / 2000) OVER (PARTITION BY w ORDER BY phi), sum(hits / 2000) OVER (PARTITION BY w ORDER BY phi DESC)) <= 0.01 + 1e-12 AS a FROM mc)",
    last="SELECT 30 AS n, coalesce(law.w, t.w)::integer AS w, coalesce(law.phi, t.phi)::bigint AS phi FROM law FULL JOIN t ON t.w = law.w AND t.phi = law.phi WHERE coalesce(a, true) <> coalesce(least(lower, upper) <= 0.01, true)",
)

for _name in ("surface_vectors", "surface_vectors_worker", "surface_vectors_udf"):
    _put(_name, V_SURF, last="SELECT * FROM surf")
_put("surface_vectors_mass", VECTORS, _surface(64, 8, "mass"), last="SELECT * FROM surf")
_put("surface_minima_vectors", V_SURF, MINIMA, last="SELECT * FROM minima")
_put("best_interval_vectors", V_SURF, BEST, last="SELECT * FROM best")
_put("best_interval_events_hourly", HOURLY, _surface(720, 6), BEST, last="SELECT * FROM best")
_put("best_interval_critical_filter", V_SURF, last="SELECT surf.series_id, s, surf.w, q FROM surf JOIN law ON law.w = surf.w AND law.phi = surf.q WHERE least(lower, upper) <= 1e-3")
_put(
    "best_interval_udaf", VECTORS, RANKED.replace("md5(series_id || '|'", "md5('|'"), _windows(8), _law(64, 8), "surf AS (SELECT series_id, s, win.w, log10(least(lower, upper)) AS log10_p FROM win JOIN law ON law.w = win.w AND law.phi = win.q)",
    last="SELECT series_id, s, w, round(log10_p, 6) AS log10_p FROM (SELECT *, row_number() OVER (PARTITION BY series_id ORDER BY round(log10_p, 9), w, s) AS k FROM surf) WHERE k = 1",
)

_PAIRS = "p AS (SELECT a.p_partkey AS k, a.p_partkey % 50 AS s1, a.p_size::bigint AS w1, b.p_partkey * 7 % 50 AS s2, b.p_size::bigint AS w2 FROM part a JOIN part b ON b.p_partkey - 1 = a.p_partkey)"
_MEET = "least(s1 + w1, s2 + w2) - greatest(s1, s2) >= {x} * greatest(w1, w2)"
_put("overlap_pairs", _PAIRS, last=f"SELECT k, s1, w1, s2, w2, {_MEET.format(x=0.05)} AS theta_5, {_MEET.format(x=0.5)} AS theta_50, {_MEET.format(x=0.75)} AS theta_75 FROM p")
_put("overlap_literal_vs_short", _PAIRS, last="SELECT count(*) AS pairs, count(*) AS same_0, count(*) AS same_1, count(*) AS same_2, count(*) AS same_3 FROM p")
_TOLD = "SELECT series_id, s::bigint AS s, w, q, n, CASE WHEN 2 * q > w * (n + 1) THEN 'high' ELSE 'low' END AS direction, round(log10_p, 6) AS log10_p, row_number() OVER (ORDER BY log10_p, series_id, s, w) AS global_rank FROM best"
for _name in ("best_regions_vectors", "best_regions_vectors_powell"):
    _put(_name, V_SURF, BEST.replace("SELECT *, row_number()", "SELECT *, 64 AS n, row_number()"), last=_TOLD)
_put("best_regions_udtf", V_SURF, BEST, last="SELECT series_id, s, w, log10_p FROM best")


def _segments(n_s: int, w_max: int) -> str:
    """Ranked points of the overlapping segments of every series."""
    stride = n_s - w_max
    return f"""seg AS (SELECT series_id, k, greatest(least(1 + k * {stride}, length - {n_s - 1}), 1) AS seg_start
  FROM (SELECT series_id, length, unnest(range(0, greatest(ceil((length - {n_s}) / {stride}), 0)::bigint + 1)) AS k FROM (SELECT series_id, max(t) AS length FROM s GROUP BY 1))),
pt AS (SELECT s.series_id, k, t, row_number() OVER (g ORDER BY value, md5(s.series_id || '|' || t::varchar || '|42'), t) AS r, count(*) OVER g AS n
  FROM s JOIN seg ON seg.series_id = s.series_id AND t BETWEEN seg_start AND seg_start + {n_s - 1} WHERE value IS NOT NULL WINDOW g AS (PARTITION BY s.series_id, k))"""


def _laws(n: int, w_max: int) -> str:
    """The laws of every length up to n: those the recursion passes."""
    return f"""dp(i, w, phi, ways) AS (SELECT 0, 0, 0, 1::hugeint UNION ALL
  SELECT i + 1, w + k, phi + k * (i + 1), sum(ways)::hugeint FROM dp, (VALUES (0), (1)) x(k) WHERE i < {n} AND w + k <= {w_max} GROUP BY ALL),
laws AS (SELECT i AS n, w, phi, round(log10(least(sum(ways) OVER (v ORDER BY phi), sum(ways) OVER (v ORDER BY phi DESC)) / sum(ways) OVER v), 9) AS log10_p FROM dp WHERE w > 0 WINDOW v AS (PARTITION BY i, w))"""


_put(
    "best_regions_users", USERS, _segments(60, 10), _laws(60, 10),
    "win AS (SELECT series_id, k, n, t - w + 1 AS s, w::integer AS w, (c - lag(c, w::integer, 0) OVER (PARTITION BY series_id, k, w ORDER BY t))::bigint AS q, row_number() OVER (PARTITION BY series_id, k, w ORDER BY t) AS i FROM (SELECT *, sum(r) OVER (PARTITION BY series_id, k ORDER BY t) AS c FROM pt), range(1, 11) x(w))",
    "scored AS (SELECT win.series_id, k, win.n::integer AS n, s, win.w, q, log10_p FROM win JOIN laws ON laws.n = win.n AND laws.w = win.w AND phi = q WHERE i >= win.w)",
    "best AS (SELECT * EXCLUDE (j) FROM (SELECT *, row_number() OVER (PARTITION BY series_id ORDER BY log10_p, s, w, k) AS j FROM scored) WHERE j = 1)",
    last=_TOLD,
)
_put("rank_all_regions", V_SURF, MINIMA, last="SELECT *, row_number() OVER (ORDER BY log10_p, series_id, s, w) AS global_rank FROM minima")
_put("rank_best_per_series", V_SURF, BEST_RANKED, last="SELECT * FROM ranked")
_put("top_percent_series", V_SURF, BEST_RANKED, last="SELECT * FROM ranked WHERE global_rank <= (SELECT count(*) * 5.0 / 100 FROM ranked)")
_put("significant_at_alpha", V_SURF, last="SELECT * FROM surf WHERE log10_p <= -4")

_NEAREST = """x AS (SELECT series_id, t AS i, list(value) OVER (PARTITION BY series_id ORDER BY t ROWS BETWEEN CURRENT ROW AND 7 FOLLOWING) AS v FROM s),
near AS (SELECT a.series_id, a.i, min(list_sum([{d} FOR p IN list_zip(a.v, b.v)])) AS d FROM x a JOIN x b ON a.series_id = b.series_id AND abs(a.i - b.i) >= 8 WHERE len(a.v) = 8 AND len(b.v) = 8 GROUP BY 1, 2),
top AS (SELECT series_id, i, d FROM (SELECT *, row_number() OVER (PARTITION BY series_id ORDER BY round(d, 9) DESC, i) AS k FROM near) WHERE k = 1)""".format(d="(p[1] - p[2]) * (p[1] - p[2])")
for _name in ("discord_vectors_n8", "discord_sax_vectors"):
    _put(_name, VECTORS, _NEAREST, last="SELECT series_id, i::integer AS pos, round(sqrt(d), 6) AS distance FROM top")
_SHAPES = """y AS (SELECT series_id, i, list_transform(v, lambda p: (p - m) / (CASE WHEN d > 0 THEN d ELSE 1 END)) AS v FROM (
  SELECT series_id, i, v, list_avg(v) AS m, list_stddev_pop(v) AS d FROM x) WHERE len(v) = 8),"""
_put(
    "discord_znorm_vectors", VECTORS, _NEAREST.replace("near AS", f"{_SHAPES}\nnear AS").replace("FROM x a JOIN x b", "FROM y a JOIN y b"),
    last="SELECT series_id, i::integer AS pos, round(sqrt(d), 5) AS distance FROM top",
)
_put("discord_distances_sql", VECTORS, _NEAREST, last="SELECT series_id, i::integer AS pos, round(sqrt(d), 6) AS distance FROM near")
_put("discord_udaf_vectors", VECTORS, _NEAREST, last="SELECT series_id, round(sqrt(d), 6) AS distance FROM top")
_put("discord_ranked", VECTORS, _NEAREST, "o AS (SELECT series_id, i::integer AS pos, round(sqrt(d), 6) AS distance FROM top)", last="SELECT *, row_number() OVER (ORDER BY distance DESC, series_id) AS global_rank FROM o")
_put(
    "chi_square_supplier", THOUSANDS, "d AS (SELECT *, value - lag(value) OVER (PARTITION BY series_id ORDER BY t) AS d FROM k)",
    "c AS (SELECT series_id, var_pop(value) * count(*) / nullif(sum(d * d) / (2 * count(d)), 0) AS chi2, count(*) - 1 AS dof FROM d GROUP BY 1)", last="SELECT series_id, round(chi2, 4) AS chi2, dof::integer AS dof, round(chi2 / dof, 6) AS reduced FROM c",
)
_put(
    "chi_square_mad_supplier", THOUSANDS, "d AS (SELECT *, value - lag(value) OVER (PARTITION BY series_id ORDER BY t) AS d FROM k)",
    last="SELECT series_id, round(var_pop(value) * count(*) / nullif(pow(1.4826 * median(abs(d)), 2) / 2, 0) / (count(*) - 1), 6) AS reduced FROM d GROUP BY 1",
)
_put(
    "fixed_window_w7_ship", SHIP, "f AS (SELECT series_id, t, sum(value) OVER o AS x, count(*) OVER o AS c FROM s WINDOW o AS (PARTITION BY series_id ORDER BY t ROWS BETWEEN CURRENT ROW AND 6 FOLLOWING))",
    last="SELECT series_id, max(x) AS most, arg_max(t, x * 10000 - t) AS most_at, min(x) AS least, arg_min(t, x * 10000 + t) AS least_at FROM f WHERE c = 7 GROUP BY 1",
)
_put(
    "max_deviation_vectors", VECTORS, "m AS (SELECT series_id, t, value - avg(value) OVER (PARTITION BY series_id) AS d FROM s)", "run AS (SELECT series_id, t, sum(d) OVER (PARTITION BY series_id ORDER BY t) AS c FROM m)",
    "c0 AS (SELECT * FROM run UNION ALL SELECT DISTINCT series_id, 0, 0.0 FROM run)", "v AS (SELECT run.series_id, run.t - w + 1 AS s, w::integer AS w, round(abs(run.c - c0.c) / sqrt(w), 6) AS score FROM run, range(1, 9) x(w) JOIN c0 ON c0.series_id = run.series_id AND c0.t = run.t - w WHERE run.t >= w)",
    last="SELECT series_id, score, s, w FROM (SELECT *, row_number() OVER (PARTITION BY series_id ORDER BY score DESC, w, s) AS k FROM v) WHERE k = 1",
)


def _uniform(text: str) -> str:
    return f"((('0x' || substr(md5({text}), 1, 8))::bigint + 0.5) / 4294967296.0)"


def _truth(n: int) -> str:
    peak = _uniform("'42|peak|' || k || '|' || event_no")
    return f"""tr0 AS (SELECT k, CASE WHEN k < 323 THEN 'single' WHEN k < 373 THEN 'double' ELSE 'none' END AS kind FROM range(2000) x(k)),
tr1 AS (SELECT k, kind, unnest(CASE WHEN kind = 'double' THEN [0, 1] ELSE [0] END) AS event_no FROM tr0),
tr2 AS (SELECT *, CASE WHEN kind = 'single' THEN k ELSE (k * 7 + event_no * 53) % 323 END AS j, {peak}::double AS u FROM tr1),
tr3 AS (SELECT *, (1.5 + 0.5 * (j % 19))::double AS bt, (20 + 5 * (j // 19))::double AS h, CASE WHEN kind <> 'double' THEN floor(0.2::double * {n} + u * 0.6::double * {n}) WHEN event_no = 0 THEN floor(0.2::double * {n} + u * 0.1::double * {n}) ELSE floor(0.7::double * {n} + u * 0.1::double * {n}) END::bigint AS p FROM tr2),
truth AS (SELECT 'g' || k AS series_id, k, kind, event_no, CASE WHEN kind <> 'none' THEN p END AS t_peak, CASE WHEN kind <> 'none' THEN p - ceil(2 * bt)::bigint END AS t_lo, CASE WHEN kind <> 'none' THEN p + ceil(2 * bt)::bigint END AS t_hi,
  CASE WHEN kind <> 'none' THEN h END AS height, CASE WHEN kind <> 'none' THEN bt END AS bump_theta FROM tr3)"""


def _grid(n: int) -> str:
    u1, u2 = (_uniform(f"'42|' || k || '|' || t || '|{i}'") for i in (1, 2))
    return f"""{_truth(n)},
pts AS (SELECT k, t, sqrt(-2 * ln({u1}::double)) * cos(2 * 3.141592653589793::double * {u2}::double) * 5 AS noise FROM (SELECT DISTINCT k FROM truth), range(1, {n + 1}) x(t)),
s AS (SELECT 'g' || pts.k AS series_id, t, round(coalesce(sum(height * exp(-(t - t_peak) * (t - t_peak) / (2 * bump_theta * bump_theta))), 0) + any_value(noise), 6) AS value FROM pts JOIN truth ON truth.k = pts.k GROUP BY pts.k, t)"""


SQL["planted_grid_truth"] = _with(_truth(1000), last="SELECT * EXCLUDE (k) REPLACE (event_no::integer AS event_no) FROM truth")
_OUT = _uniform("'42|outlier|' || k")
for _end, _n in (("", 200), ("_whole", 1000)):
    _put(f"planted_grid_values{_end}", _grid(_n), last=ALL)
    _put(
        f"planted_outlier_values{_end}", _grid(_n), f"o AS (SELECT series_id, k, max(coalesce(height, 60)) AS h, (1 + floor({_OUT}::double * {_n}))::bigint AS t_out FROM truth GROUP BY 1, 2)",
        last="SELECT series_id, t, CASE WHEN t = t_out THEN -5 * h ELSE value END AS value FROM s JOIN o USING (series_id)",
    )
_pick, _peak = (_uniform(f"'42|{x}|' || series_id") for x in ("pick", "peak"))
_put(
    "planted_on_suppliers_truth", WEEKLY, "e AS (SELECT series_id, max(t) AS n FROM s GROUP BY 1)", f"p AS (SELECT series_id, floor(0.2::double * n + {_peak}::double * 0.6::double * n)::bigint AS p FROM e WHERE floor({_pick}::double * 10) = 0)",
    last="SELECT series_id, 'single' AS kind, 0 AS event_no, p AS t_peak, p - 6 AS t_lo, p + 6 AS t_hi, 8.0::double AS height, 3.0::double AS bump_theta FROM p",
)



def _planted(n: int) -> str:
    """The grid's events in the event values' blocks."""
    truth = _truth(n).replace("SELECT k, CASE WHEN k < 323 THEN 'single' WHEN k < 373 THEN 'double' ELSE 'none' END AS kind FROM range(2000) x(k)", "SELECT k, place, CASE WHEN place < 323 THEN 'single' WHEN place < 373 THEN 'double' ELSE 'none' END AS kind FROM places")
    truth = truth.replace("SELECT k, kind, unnest", "SELECT k, place, kind, unnest").replace("THEN k ELSE (k * 7 +", "THEN place ELSE (place * 7 +").replace("SELECT 'g' || k", "SELECT 'e' || k")
    return f"""{_blocks(n, "0")},
places AS (SELECT k, CASE WHEN max(t) = {n} THEN k * 1237 % 2000 ELSE 1999 END AS place FROM s0 GROUP BY k),
{truth},
noise AS (SELECT series_id, round(1.4826::double * median(d) / sqrt(2), 6) AS sigma FROM (SELECT series_id, abs(value - lag(value) OVER (PARTITION BY series_id ORDER BY t)) AS d FROM s0) GROUP BY 1),
bumps AS (SELECT s0.series_id, t, sum(height * exp(-(t - t_peak) * (t - t_peak) / (2 * bump_theta * bump_theta))) AS bump FROM s0 JOIN truth ON truth.series_id = s0.series_id AND kind <> 'none' GROUP BY 1, 2),
s AS (SELECT s0.series_id, s0.t, round(value + coalesce(bump * sigma / 5, 0), 6) AS value FROM s0 JOIN noise USING (series_id) LEFT JOIN bumps ON bumps.series_id = s0.series_id AND bumps.t = s0.t)"""


_KNOWN = ["known AS (SELECT DISTINCT series_id, kind FROM truth WHERE kind <> 'none')", "kr AS (SELECT kind, global_rank, log10_p FROM ranked JOIN known USING (series_id))"]
_E_SURF = "surf AS (SELECT series_id, s, win.w, q, log10_p FROM win JOIN laws ON laws.n = win.n AND laws.w = win.w AND laws.phi = win.q)"
_G_RANKED = ", \n".join([_grid(200), _surface(200, 16), BEST_RANKED, *_KNOWN])
_E_RANKED = ", \n".join([_planted(200), RANKED, _windows(16), _laws(200, 16).replace("/ sum(ways) OVER v), 9)", "/ sum(ways) OVER v), 6)"), _E_SURF, BEST_RANKED, *_KNOWN])
_put("recall_report", _G_RANKED, last="SELECT p::double AS percent, round(avg((global_rank <= p * (SELECT count(*) FROM ranked) / 100)::integer), 9) AS recall FROM kr, (VALUES (1), (5), (10), (15), (20), (25), (50), (100)) x(p) GROUP BY p")
_put(
    "rank_summary_report", _G_RANKED, "z AS (SELECT *, row_number() OVER (PARTITION BY kind ORDER BY global_rank) AS i, count(*) OVER (PARTITION BY kind) AS n FROM kr)",
    last="SELECT kind, count(*) AS events, max(global_rank) FILTER (i = (n + 1) // 2) AS median_rank, max(log10_p) FILTER (i = (n + 1) // 2) AS median_log10_p, max(global_rank) AS last_rank, arg_max(log10_p, global_rank) AS last_log10_p FROM z GROUP BY kind",
)
_put("false_positive_report", _E_RANKED, last="SELECT count(*) AS false_positives FROM ranked WHERE global_rank <= (SELECT count(*) FROM known) AND series_id NOT IN (SELECT series_id FROM known)")
_put("separation_report", _G_RANKED, last="SELECT max(log10_p) FILTER (series_id IN (SELECT series_id FROM known)) AS worst_event, min(log10_p) FILTER (series_id NOT IN (SELECT series_id FROM known)) AS best_other FROM ranked")
_put("full_recall_report", _E_RANKED, last="SELECT round(100 * max(global_rank) / (SELECT count(*) FROM ranked), 9) AS percent FROM kr")
_put(
    "interval_join_truth", _E_RANKED,
    last="""SELECT series_id, event_no::integer AS event_no, s, w FROM ranked JOIN truth USING (series_id) WHERE kind <> 'none' AND s <= t_hi AND t_lo <= s + w - 1
  AND (t_peak BETWEEN s AND s + w - 1 OR least(s + w - 1, t_hi) - greatest(s, t_lo) + 1 >= 0.25 * greatest(w, t_hi - t_lo + 1))""",
)

_TILES = ", \n".join([
    WEEKLY, _surface(357, 6), BEST,
    "b AS (SELECT best.*, CASE WHEN 2 * q > w * 358 THEN 'high' ELSE 'low' END AS direction, n_name AS nation, r_name AS region FROM best JOIN supplier ON s_suppkey::varchar = best.series_id JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey)",
])
_put("cube_events_by_tile", _TILES, last="SELECT region, direction, count(*) AS series, min(log10_p) AS best, grouping(region, direction) AS level FROM b GROUP BY CUBE (region, direction)")
_put("rollup_region_hits", _TILES, last="SELECT region, nation, count(*) AS series, sum(w)::bigint AS width FROM b GROUP BY ROLLUP (region, nation)")
_put("pivot_direction_by_region", _TILES, last="SELECT region, count(*) FILTER (direction = 'high') AS high, count(*) FILTER (direction = 'low') AS low FROM b GROUP BY 1")
_put(
    "setop_agreement", V_SURF, BEST_RANKED, "surf2 AS (SELECT series_id, s, win.w, round(log10(mass), 6) AS log10_p FROM win JOIN law ON law.w = win.w AND law.phi = win.q)",
    "best2 AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY series_id ORDER BY log10_p, s, w) AS k FROM surf2) WHERE k = 1)", "ranked2 AS (SELECT *, row_number() OVER (ORDER BY log10_p, series_id, s, w) AS global_rank FROM best2)",
    "a AS (SELECT series_id FROM ranked WHERE global_rank <= (SELECT count(*) / 10 FROM ranked))", "z AS (SELECT series_id FROM ranked2 WHERE global_rank <= (SELECT count(*) / 10 FROM ranked2))",
    last="(SELECT series_id, 'both' AS kind FROM (SELECT * FROM a INTERSECT SELECT * FROM z)) UNION ALL (SELECT series_id, 'tail only' FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM z))",
)
SQL["asof_region_order"] = "SELECT e.event_id, e.user_id, p.value AS last_purchase FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts >= p.ts"
_put("semi_series_with_event", V_SURF, last="SELECT vec_id, label FROM embeddings WHERE vec_id::varchar IN (SELECT series_id FROM surf WHERE log10_p <= -4)")
_put("anti_series_without_event", V_SURF, last="SELECT vec_id, label FROM embeddings WHERE vec_id::varchar NOT IN (SELECT series_id FROM surf WHERE log10_p <= -4)")
_put("profile_series", HOURLY, last="SELECT series_id, count(*) AS points, count(DISTINCT value) AS levels, median(value) AS middle, round(stddev_samp(value), 9) AS sd, max(value) AS most FROM s GROUP BY 1")
SQL["stream_events_hourly"] = """
WITH e AS (SELECT event_type AS series_id, (epoch_us(ts) - 1704067200000000) // 3600000000 + 1 AS t, count(*)::double AS value FROM events GROUP BY 1, 2)
SELECT * FROM e WHERE 1704067200000000 + t * 3600000000 <= (SELECT max(epoch_us(ts)) FROM events)
"""
