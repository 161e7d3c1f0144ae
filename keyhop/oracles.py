"""DuckDB SQL for measures of the five-attribute table, from brute force on the key's bits.

The SQL derives the codes, the interleaved key and the restrictions from the table itself. The next
match of a key is found by trying every bit that is zero in it: raise the bit, clear what is below,
complete each restricted attribute by its least allowed value, and keep what is allowed. Nothing of it
shares a formula with the engine.
"""

from __future__ import annotations

import datetime as dt

from keyhop.plans.filters import Between, Eq, Filter, In

#: Attribute: the expression of its value in units of a code, in alphabetical order.
UNITS = {"l_discount": "round(l_discount * 100)", "l_partkey": "l_partkey", "l_quantity": "l_quantity", "l_shipdate": "date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE))", "l_suppkey": "l_suppkey"}
_NAMES = list(UNITS)


def _unit(name: str, value) -> str:
    if isinstance(value, dt.date):
        return str((value - dt.date(1970, 1, 1)).days)
    return repr(round(value * 100) if name == "l_discount" else value)


def _intervals(name: str, f: Filter) -> str:
    """The allowed codes as a list of [from, to], clipped to the domain."""
    code = lambda v: f"({_unit(name, v)} - e.lo + 1)"
    if isinstance(f, Eq | In):
        ends = [(code(v), code(v)) for v in (f.values if isinstance(f, In) else (f.value,))]
    elif isinstance(f, Between):
        ends = [(code(f.lo) if f.lo is not None else "1", code(f.hi) if f.hi is not None else "e.size")]
    else:
        raise ValueError(type(f))
    listed = ", ".join(f"[CAST(greatest(1, ceil({a})) AS BIGINT), CAST(least(e.size, floor({b})) AS BIGINT)]" for a, b in ends)
    return f"list_filter([{listed}], lambda x: x[1] <= x[2])"


def keys_sql() -> str:
    """CTEs: ``ends`` (domains), ``places`` (key bit of each code bit, both from 0), ``total`` (key bits) and ``coded`` (distinct keys with their numbers of rows)."""
    units = ", ".join(f"CAST({u} AS BIGINT) AS u{i}" for i, u in enumerate(UNITS.values()))
    ends = " UNION ALL ".join(f"SELECT {i} AS i, '{n}' AS name, min(u{i}) AS lo, max(u{i}) - min(u{i}) + 1 AS size FROM units" for i, n in enumerate(_NAMES))
    shifted = " + ".join(f"list_sum(list_transform(p.p{i}, lambda x: ((u{i} - p.lo{i} + 1) >> x[1] & 1) << x[2]))" for i in range(len(_NAMES)))
    picked = ", ".join(f"list([CAST(cb AS BIGINT), CAST(kb AS BIGINT)]) FILTER (i = {i}) AS p{i}, any_value(lo) FILTER (i = {i}) AS lo{i}" for i in range(len(_NAMES)))
    return f"""units AS (SELECT {units} FROM lineitem),
ends AS ({ends}),
ranked AS (SELECT *, CAST(floor(log2(size)) AS BIGINT) + 1 AS b FROM ends),
ordered AS (SELECT *, row_number() OVER (ORDER BY b DESC, size DESC, name) AS place FROM ranked),
total AS (SELECT CAST(sum(b) AS BIGINT) AS n FROM ranked),
places AS (SELECT i, b - 1 - j AS cb, (SELECT n FROM total) - row_number() OVER (ORDER BY j, place) AS kb FROM ordered, range(64) r(j) WHERE j < b),
picked AS (SELECT {picked} FROM places JOIN ends USING (i)),
coded AS (SELECT CAST({shifted} AS BIGINT) AS k, count(*) AS m FROM units, picked p GROUP BY 1)"""


def marked_sql(filters: dict[str, Filter]) -> str:
    """CTEs up to ``marked``: ``k``, ``m``, ``y`` (highest failing key bit from 1; 0 for a match) and ``h`` (next match) within the bounds."""
    restricted = " UNION ALL ".join(f"SELECT {_NAMES.index(n)} AS i, {_intervals(n, f)} AS allowed FROM ends e WHERE e.i = {_NAMES.index(n)}" for n, f in filters.items())
    least = lambda v: f"list_min(list_transform(list_filter(allowed, lambda x: x[2] >= {v}), lambda x: greatest(x[1], {v})))"
    greatest = "list_max(list_transform(allowed, lambda x: x[2]))"
    return f"""{keys_sql()},
restricted AS ({restricted}),
held AS (SELECT r.i, any_value(r.allowed) AS allowed, list([CAST(cb AS BIGINT), CAST(kb AS BIGINT)] ORDER BY cb) AS bits FROM restricted r JOIN places USING (i) GROUP BY r.i),
masks AS (SELECT *, list_sum(list_transform(bits, lambda x: CAST(1 AS BIGINT) << x[2])) AS mask FROM held),
bounds AS (SELECT CAST(sum(list_sum(list_transform(bits, lambda x: ({least('0')} >> x[1] & 1) << x[2]))) AS BIGINT) AS lo,
  CAST((SELECT (CAST(1 AS BIGINT) << n) - 1 FROM total) - sum(mask) + sum(list_sum(list_transform(bits, lambda x: ({greatest} >> x[1] & 1) << x[2]))) AS BIGINT) AS hi, min(list_min(list_transform(bits, lambda x: x[2]))) AS tail FROM masks),
inside AS (SELECT k, m FROM coded, bounds WHERE k BETWEEN bounds.lo AND bounds.hi),
valued AS (SELECT k, m, i, allowed, bits, CAST(list_sum(list_transform(bits, lambda x: (k >> x[2] & 1) << x[1])) AS BIGINT) AS v FROM inside, masks),
failed AS (SELECT k, m, coalesce(max(list_max(list_transform(list_filter(bits, lambda b: NOT list_bool_or(list_transform(allowed, lambda a: a[1] <= ((v >> b[1]) << b[1]) + (1 << b[1]) - 1 AND a[2] >= (v >> b[1]) << b[1]))), lambda b: b[2] + 1))), 0) AS y FROM valued GROUP BY k, m),
tried AS (SELECT k, t, CAST(((k >> t) | 1) << t AS BIGINT) AS raised FROM failed, total, range(63) r(t) WHERE y > 0 AND t < n AND (k >> t) & 1 = 0),
based AS (SELECT k, t, raised, allowed, bits, CAST(list_sum(list_transform(bits, lambda x: (raised >> x[2] & 1) << x[1])) AS BIGINT) AS v, len(list_filter(bits, lambda x: x[2] < t)) AS low FROM tried, masks),
completed AS (SELECT k, t, raised, bits, low, v, {least('v')} AS c FROM based),
candidates AS (SELECT k, t, any_value(raised) + CAST(sum(list_sum(list_transform(bits, lambda x: (c >> x[1] & 1) << x[2])) - list_sum(list_transform(bits, lambda x: (v >> x[1] & 1) << x[2]))) AS BIGINT) AS h FROM completed GROUP BY k, t HAVING bool_and(c IS NOT NULL AND c >> low = v >> low)),
following AS (SELECT k, min(h) AS h FROM candidates GROUP BY k),
marked AS (SELECT k, m, y, h FROM failed LEFT JOIN following USING (k))"""


def crawl_sql(filters: dict[str, Filter]) -> str:
    return f"WITH {marked_sql(filters)} SELECT CAST(coalesce(sum(m) FILTER (y = 0), 0) AS BIGINT) AS matched, CAST(coalesce(sum(m) FILTER (y > 0), 0) AS BIGINT) AS scans, CAST(0 AS BIGINT) AS jumps FROM marked"


def leap_sql(filters: dict[str, Filter]) -> str:
    return f"WITH {marked_sql(filters)} SELECT CAST(coalesce(sum(m) FILTER (y = 0), 0) AS BIGINT) AS matched, CAST(0 AS BIGINT) AS scans, count(DISTINCT h) FILTER (y > 0) AS jumps FROM marked"


def counters_sql(filters: dict[str, Filter], thresholds: str) -> str:
    """CTEs up to ``counted``: counters by threshold; ``thresholds`` is a query that gives column ``t``."""
    return f"""WITH {marked_sql(filters)},
wanted AS ({thresholds}),
firsts AS (SELECT t, h, min(k) FILTER (y > t) AS first FROM marked, wanted WHERE y > 0 GROUP BY t, h),
counted AS (SELECT CAST(w.t AS INTEGER) AS threshold, (SELECT CAST(coalesce(sum(m), 0) AS BIGINT) FROM marked WHERE y = 0) AS matched,
  (SELECT CAST(coalesce(sum(m), 0) AS BIGINT) FROM marked x JOIN firsts f ON f.h = x.h WHERE f.t = w.t AND x.y > 0 AND (f.first IS NULL OR x.k < f.first)) AS scans,
  (SELECT count(first) FROM firsts f WHERE f.t = w.t) AS jumps FROM wanted w)"""


def rows_threshold_sql(ratio: float) -> str:
    """The threshold from the number of rows, for the restricted attributes' masks."""
    return f"least(greatest(CAST(ceil(n - log2(greatest((SELECT sum(m) FROM coded) * {ratio}, 1))) AS BIGINT), 0, (SELECT tail FROM bounds)), n)"


def regions_sql(senior: int) -> str:
    """Rows by the ``senior`` highest key bits."""
    return f"WITH {keys_sql()} SELECT k >> (n - {senior}) AS region, CAST(sum(m) AS BIGINT) AS rows FROM coded, total GROUP BY 1"


def first_sql(filters: dict[str, Filter], rows: int) -> str:
    """The first keys that match, as often as they occur."""
    return f"WITH {marked_sql(filters)} SELECT k AS k0 FROM marked, range(CAST(m AS BIGINT)) r(i) WHERE y = 0 ORDER BY k LIMIT {rows}"


def cofrequency_sql(name: str) -> str:
    """Over the rows, the mean number of values of an attribute in a gap of whose keys the row's key lies, by trying all values."""
    return f"""WITH {keys_sql()},
bits AS (SELECT list([CAST(cb AS BIGINT), CAST(kb AS BIGINT)]) AS held, list_sum(list(CAST(1 AS BIGINT) << kb)) AS mask, CAST(count(*) AS BIGINT) AS d FROM places WHERE i = {_NAMES.index(name)}),
patterns AS (SELECT CAST(list_sum(list_transform(held, lambda x: (p >> x[1] & 1) << x[2])) AS BIGINT) AS pattern, mask, (CAST(1 AS BIGINT) << n) - 1 - mask AS free FROM bits, total, range(1 << d) r(p)),
met AS (SELECT k, any_value(m) AS m, count(*) FILTER (pattern < k AND k < pattern + free AND k & CAST(mask AS BIGINT) <> pattern) AS c FROM coded, patterns GROUP BY k)
SELECT sum(c * m) / sum(m) AS mean_cofrequency FROM met"""


def lacunae_sql() -> str:
    """Clusters and gaps of a point on each attribute, from the islands of its key bits."""
    return f"""WITH {keys_sql()},
islands AS (SELECT i, kb, kb - row_number() OVER (PARTITION BY i ORDER BY kb) AS island FROM places),
parts AS (SELECT i, min(kb) AS t, max(kb) + 1 AS h FROM islands GROUP BY i, island),
gaps AS (SELECT a.i, a.t, CAST(sum((CAST(1 AS BIGINT) << b.h) - (CAST(1 AS BIGINT) << b.t)) AS BIGINT) AS gap FROM parts a JOIN parts b ON a.i = b.i AND b.t <= a.t GROUP BY a.i, a.t),
listed AS (SELECT i, list(gap ORDER BY t DESC) AS gaps FROM gaps GROUP BY i),
shapes AS (SELECT i, count(*) AS d, min(kb) AS t, CAST(sum(CAST(1 AS BIGINT) << kb) AS BIGINT) AS mask FROM places GROUP BY i)
SELECT name AS attribute, CAST(1 AS BIGINT) << (n - d - t) AS clusters, CAST(1 AS BIGINT) << t AS cluster_length, (CAST(1 AS BIGINT) << n) - mask - (CAST(1 AS BIGINT) << (n - d)) AS gap_total, gaps FROM shapes JOIN listed USING (i) JOIN ends USING (i), total"""
