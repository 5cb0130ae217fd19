"""DuckDB fragments that the oracles share."""

from __future__ import annotations

from stratafit.functions.portable import sql_uniform

HOUR = "(date_diff('day', DATE '1970-01-01', {0}::DATE) * 24 + hour({0}))"
DAY = "date_diff('day', DATE '1970-01-01', {0}::DATE)"
MONTH = "((year({0}) - 1970) * 12 + month({0}) - 1)"


def cents(x: str) -> str:
    return f"CAST(round({x} * 100) AS BIGINT)"


def points(cells: str, fill: str = "zero") -> str:
    """CTEs up to points (series_id, t, bucket, z) from a SELECT of series_id, bucket, z."""
    spine = """spine AS (SELECT series_id, lo, unnest(generate_series(lo, hi)) AS bucket FROM (SELECT DISTINCT series_id FROM cells), span),
full_points AS (SELECT s.series_id, s.bucket - s.lo AS t, s.bucket, c.z FROM spine s LEFT JOIN cells c ON c.series_id = s.series_id AND c.bucket = s.bucket)"""
    last = {
        "zero": "points AS (SELECT series_id, t, bucket, coalesce(z, 0) AS z FROM full_points)",
        "ffill": "points AS (SELECT * FROM (SELECT series_id, t, bucket, last_value(z IGNORE NULLS) OVER (PARTITION BY series_id ORDER BY t) AS z FROM full_points) WHERE z IS NOT NULL)",
        "drop": "points AS (SELECT series_id, bucket - lo AS t, bucket, z FROM cells, span)",
    }[fill]
    return f"cells AS ({cells}), span AS (SELECT min(bucket) AS lo, max(bucket) AS hi FROM cells),\n" + (last if fill == "drop" else f"{spine},\n{last}")


S1 = points(f"SELECT event_type AS series_id, {HOUR.format('ts')} AS bucket, sum({cents('value')})::BIGINT AS z FROM events GROUP BY 1, 2")
S2 = points(f"SELECT ((user_id % 8 + 8) % 8)::VARCHAR AS series_id, {HOUR.format('ts')} AS bucket, sum({cents('value')})::BIGINT AS z FROM events GROUP BY 1, 2")
_COUNTS = points(f"SELECT event_type AS series_id, {HOUR.format('ts')} AS bucket, count(*)::BIGINT AS z FROM events GROUP BY 1, 2").replace("points AS", "counts AS").replace("full_counts AS", "full_points AS")
S3 = _COUNTS + ",\npoints AS (SELECT series_id, t, bucket, coalesce(z::DOUBLE / nullif(sum(z) OVER (PARTITION BY t), 0)::DOUBLE, 0.0) AS z FROM counts)"
_ORDERS = "orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey"
S4 = points(f"SELECT n_regionkey::VARCHAR AS series_id, {DAY.format('o_orderdate')} AS bucket, sum({cents('o_totalprice')})::BIGINT AS z FROM {_ORDERS} GROUP BY 1, 2")
S5 = points(f"SELECT c_nationkey::VARCHAR AS series_id, {DAY.format('o_orderdate')} AS bucket, (sum({cents('o_totalprice')}) // count(*))::BIGINT AS z FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1, 2", "ffill")
S6 = points(f"SELECT s_nationkey::VARCHAR AS series_id, {MONTH.format('l_shipdate')} AS bucket, sum({cents('l_extendedprice')})::BIGINT AS z FROM lineitem JOIN supplier ON s_suppkey = l_suppkey GROUP BY 1, 2")
S7 = points(f"SELECT l_suppkey::VARCHAR AS series_id, {DAY.format('l_shipdate')} AS bucket, sum(CAST(round(l_quantity) AS BIGINT))::BIGINT AS z FROM lineitem GROUP BY 1, 2", "drop")

SCALED = "scaled AS (SELECT series_id, t, bucket, z::DOUBLE / (SELECT sum(abs(z))::DOUBLE / count(*)::DOUBLE FROM points) AS z FROM points)"


def examples(source: str = "scaled", order: int = 2, name: str = "ex") -> str:
    lags = ", ".join(f"lag(z, {j}) OVER w AS x{j}" for j in range(1, order + 1))
    return f"{name} AS (SELECT * FROM (SELECT series_id, t - 1 AS t0, bucket, z::DOUBLE AS y, {lags} FROM {source} WINDOW w AS (PARTITION BY series_id ORDER BY t)) WHERE x{order} IS NOT NULL)"


def assigned(key: str, source: str = "ex", name: str = "assigned") -> str:
    """Strata numbered densely in the order of key, a comma list of expressions."""
    return f"{name} AS (SELECT *, dense_rank() OVER (ORDER BY {key}) - 1 AS stratum FROM {source})"


LAYOUT = """strata AS (SELECT stratum, count(*) AS n, count(*)::DOUBLE / (SELECT count(*) FROM assigned) AS w FROM assigned GROUP BY 1),
placed AS (SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY series_id, t0) - 1 AS pos, row_number() OVER (ORDER BY series_id, t0) - 1 AS gpos FROM assigned)"""


def gradients(theta: tuple[float, float], source: str = "assigned", name: str = "grads") -> str:
    return f"{name} AS (SELECT *, r * r AS loss, 2.0 * x1 * r AS g1, 2.0 * x2 * r AS g2 FROM (SELECT *, {theta[0]!r} * x1 + {theta[1]!r} * x2 - y AS r FROM {source}))"


def dependency(grads: str = "grads") -> str:
    """A SELECT of strata, total, within, stratified, mean_inside."""
    return f"""SELECT count(*) AS strata, any_value(total) AS total, sum(n * v)::DOUBLE / any_value(all_n) AS within, sum((n::DOUBLE / all_n) * (n::DOUBLE / all_n) * v) AS stratified, avg(v) AS mean_inside
FROM (SELECT stratum, count(*) AS n, var_pop(g1) + var_pop(g2) AS v FROM {grads} GROUP BY 1), (SELECT count(*) AS all_n, var_pop(g1) + var_pop(g2) AS total FROM {grads})"""


def position(u: str, n: str) -> str:
    return f"least(floor({u} * {n})::BIGINT, {n} - 1)"


def draw(*parts: str) -> str:
    return sql_uniform(*parts)
