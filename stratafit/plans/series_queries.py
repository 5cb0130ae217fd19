"""Series, segments, strata and draws."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from stratafit.functions import portable
from stratafit.functions.portable import sql_uniform
from stratafit.operators import sampling, series, strata
from stratafit.plans import sql_parts as P
from stratafit.plans.catalogue import register
from stratafit.sources.tables import day_number, table


def _plain(make):
    return lambda spark, d: make(spark, d).select("series_id", "t", F.col("z").cast("long").alias("z"))


for _name, _make, _sql in (
    ("hourly_series_by_type", series.hourly_by_type, P.S1), ("hourly_series_by_bucket", series.hourly_by_bucket, P.S2), ("daily_series_by_region", series.daily_by_region, P.S4),
    ("monthly_series_by_nation", series.monthly_by_nation, P.S6), ("daily_series_by_supplier", series.daily_by_supplier, P.S7),
):
    register(_name, _plain(_make), f"WITH {_sql} SELECT series_id, t::BIGINT AS t, z::BIGINT AS z FROM points")
register("hourly_share_by_type", lambda s, d: series.hourly_share(s, d).select("series_id", "t", F.round("z", 6).alias("z")), f"WITH {P.S3} SELECT series_id, t::BIGINT AS t, round(z, 6) AS z FROM points")
register(
    "daily_series_by_nation_ffill", lambda s, d: series.daily_by_nation(s, d).select("series_id", "t", F.round(F.col("z") / 1e6, 6).alias("z")),
    f"WITH {P.S5} SELECT series_id, t::BIGINT AS t, round(z / 1e6, 6) AS z FROM points",
)


def magnitude_scale(spark, d):
    found = None
    for kind in ("mean_abs", "max_abs", "zscore"):
        one = series.fit_scale(series.hourly_by_type(spark, d), kind).select("series_id", F.lit(kind).alias("kind"), F.round(F.col("shift") / 1e4, 6).alias("shift"), F.round(F.col("scale") / 1e4, 6).alias("scale"))
        found = one if found is None else found.unionByName(one)
    return found


register(
    "magnitude_scale", magnitude_scale,
    f"""WITH {P.S1}, s AS (SELECT series_id, sum(abs(z))::DOUBLE / count(*) AS ma, max(abs(z))::DOUBLE AS mx, avg(z::DOUBLE) AS av, stddev_pop(z::DOUBLE) AS sd FROM points GROUP BY 1)
SELECT series_id, 'mean_abs' AS kind, 0.0::DOUBLE AS shift, round(ma / 1e4, 6) AS scale FROM s UNION ALL SELECT series_id, 'max_abs', 0.0, round(mx / 1e4, 6) FROM s
UNION ALL SELECT series_id, 'zscore', round(av / 1e4, 6), round(sd / 1e4, 6) FROM s""",
)


def split_counts(spark, d):
    train, test = series.split_by_time(series.hourly_by_type(spark, d), 600, 72)
    train, test = train.select("series_id", "t", F.lit("train").alias("part")), test.select("series_id", "t", F.lit("test").alias("part"))
    return train.unionByName(test).groupBy("series_id", "part").agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("first_t"), F.max("t").alias("last_t"))


register(
    "split_counts", split_counts,
    f"""WITH {P.S1}, b AS (SELECT *, 'train' AS part FROM points WHERE t < 600 UNION ALL SELECT *, 'test' FROM points WHERE t >= 528)
SELECT series_id, part, count(*) AS n, min(t)::BIGINT AS first_t, max(t)::BIGINT AS last_t FROM b GROUP BY 1, 2""",
)
register(
    "segments_ar2", lambda s, d: series.lag_examples(series.monthly_by_nation(s, d), 2).select("series_id", "t0", *[F.col(c).cast("long").alias(c) for c in ("y", "x1", "x2")]),
    f"WITH {P.S6}, {P.examples('points')} SELECT series_id, t0::BIGINT AS t0, y::BIGINT AS y, x1::BIGINT AS x1, x2::BIGINT AS x2 FROM ex",
)


def _summary(make, tau_c, tau_p, scale):
    def query(spark, d):
        s = series.segments(make(spark, d), tau_c, tau_p)
        total = lambda c: F.round(F.aggregate(c, F.lit(0.0), lambda a, x: a + x) / scale, 6)
        return s.select("series_id", "t0", total("context").alias("context_sum"), F.round(F.col("context")[0] / scale, 6).alias("context_first"), F.round(F.element_at("context", -1) / scale, 6).alias("context_last"), total("target").alias("target_sum"), F.round(F.col("target")[0] / scale, 6).alias("target_first"))

    return query


def _summary_sql(points, tau_c, tau_p, scale):
    return f"""WITH {points}, q AS (SELECT series_id, t AS t0, sum(z::DOUBLE) OVER c AS cs, first_value(z::DOUBLE) OVER c AS cf, z::DOUBLE AS cl, sum(z::DOUBLE) OVER f AS ts, lead(z::DOUBLE, 1) OVER o AS tf,
  row_number() OVER o AS i, lead(z, {tau_p}) OVER o AS e FROM points
  WINDOW o AS (PARTITION BY series_id ORDER BY t), c AS (PARTITION BY series_id ORDER BY t ROWS BETWEEN {tau_c - 1} PRECEDING AND CURRENT ROW), f AS (PARTITION BY series_id ORDER BY t ROWS BETWEEN 1 FOLLOWING AND {tau_p} FOLLOWING))
SELECT series_id, t0::BIGINT AS t0, round(cs / {scale}, 6) AS context_sum, round(cf / {scale}, 6) AS context_first, round(cl / {scale}, 6) AS context_last, round(ts / {scale}, 6) AS target_sum, round(tf / {scale}, 6) AS target_first
FROM q WHERE i >= {tau_c} AND e IS NOT NULL"""


register("segments_8_1", _summary(series.daily_by_nation, 8, 1, 1e6), _summary_sql(P.S5, 8, 1, 1e6))
register("segments_72_24", _summary(series.hourly_by_type, 72, 24, 1e6), _summary_sql(P.S1, 72, 24, 1e6))


def segments_chunked(spark, d):
    chunks = series.chunk_series(series.hourly_by_type(spark, d), 256, 95)
    s = series.chunk_segments(chunks, 256, 72, 24)
    return s.select("series_id", "t0", F.round(F.aggregate("context", F.lit(0.0), lambda a, x: a + x) / 1e6, 6).alias("context_sum"), F.round(F.aggregate("target", F.lit(0.0), lambda a, x: a + x) / 1e6, 6).alias("target_sum"))


register("segments_chunked_72_24", segments_chunked, f"SELECT series_id, t0, context_sum, target_sum FROM ({_summary_sql(P.S1, 72, 24, 1e6)})")
_SETS = {"S1": (series.hourly_by_type, P.S1), "S2": (series.hourly_by_bucket, P.S2), "S4": (series.daily_by_region, P.S4), "S5": (series.daily_by_nation, P.S5), "S6": (series.monthly_by_nation, P.S6), "S7": (series.daily_by_supplier, P.S7)}


def example_counts(spark, d):
    out = None
    for name, (make, _) in _SETS.items():
        one = series.example_index(make(spark, d), 72, 24).agg(F.lit(name).alias("series_set"), F.count(F.lit(1)).alias("n_series"), F.sum("n_points").alias("n_points"), F.sum("n_examples").alias("n_examples"))
        out = one if out is None else out.unionByName(one)
    return out


register(
    "example_counts", example_counts,
    " UNION ALL ".join(f"(WITH {sql} SELECT '{name}' AS series_set, count(*) AS n_series, sum(c)::BIGINT AS n_points, sum(greatest(0, c - 95))::BIGINT AS n_examples FROM (SELECT series_id, count(*) AS c FROM points GROUP BY 1))" for name, (_, sql) in _SETS.items()),
)


def segment_features(spark, d):
    segs = series.segments(series.scaled_by_mean(series.hourly_by_type(spark, d)), 72, 24)
    f = series.segment_features(segs, (24,))
    return f.select("series_id", "t0", *[F.round(c, 6).alias(c) for c in ("mean", "std", "density", "autocorr", "spectrum_24")])


register(
    "segment_features", segment_features,
    f"""WITH {P.S1}, {P.SCALED}, m AS (SELECT max(t) AS hi FROM scaled), s AS (SELECT p.series_id, p.t AS t0 FROM scaled p, m WHERE p.t >= 71 AND p.t <= m.hi - 24),
w AS (SELECT s.series_id, s.t0, p.t - (s.t0 - 71) AS i, p.z FROM s JOIN scaled p ON p.series_id = s.series_id AND p.t BETWEEN s.t0 - 71 AND s.t0),
a AS (SELECT *, z - avg(z) OVER (PARTITION BY series_id, t0) AS dev FROM w), b AS (SELECT *, lead(dev) OVER (PARTITION BY series_id, t0 ORDER BY i) AS nxt FROM a)
SELECT series_id, t0::BIGINT AS t0, round(avg(z), 6) AS mean, round(sqrt(sum(dev * dev) / 72), 6) AS std, round(avg(CASE WHEN z <> 0 THEN 1.0 ELSE 0.0 END), 6) AS density, round(coalesce(sum(dev * nxt) / nullif(sum(dev * dev), 0), 0), 6) AS autocorr,
 round(sqrt(pow(sum(z * cos({2 * math.pi / 24!r} * i)), 2) + pow(sum(z * sin({2 * math.pi / 24!r} * i)), 2)) / 72, 6) AS spectrum_24 FROM b GROUP BY 1, 2""",
)

# Strata.


def _sizes(policy, make):
    return lambda spark, d: strata.stratum_table(policy.assign(make(spark, d))).select(F.col("stratum").cast("long").alias("stratum"), "n", F.round("w", 9).alias("w"))


def _sizes_sql(points, key, prefix=""):
    return f"WITH {points}, {prefix}{P.assigned(key)} SELECT stratum, count(*) AS n, round(count(*)::DOUBLE / (SELECT count(*) FROM ex), 9) AS w FROM assigned GROUP BY 1"


def _lagged(make):
    return lambda spark, d: series.lag_examples(make(spark, d), 2)


_EX = P.examples("points")
_S1X, _S4X, _S5X, _S6X = (f"{x}, {_EX}" for x in (P.S1, P.S4, P.S5, P.S6))
_WEEKDAY = "((bucket + 3) % 7)"
_DATE = "(DATE '1970-01-01' + bucket::INTEGER)"
_RANGE = "floor((bucket - (SELECT min(bucket) FROM ex)) * {0}::DOUBLE / ((SELECT max(bucket) FROM ex) - (SELECT min(bucket) FROM ex) + 1))::BIGINT"
_BITS = "(('0x' || substr(md5(concat_ws('|', '7', 'stratum', series_id, t0)), 1, 13))::BIGINT)"
for _name, _policy, _make, _sql in (
    ("strata_mod8", strata.ModPeriod(8), series.hourly_by_type, _sizes_sql(_S1X, "t0 % 8")),
    ("strata_weekday_year", strata.WeekdaySeason("year"), series.daily_by_region, _sizes_sql(_S4X, f"{_WEEKDAY}, year({_DATE})")),
    ("strata_weekday_ranges10", strata.WeekdaySeason(10), series.daily_by_region, _sizes_sql(_S4X, f"{_WEEKDAY}, {_RANGE.format(10)}")),
    ("strata_month_quarter", strata.CalendarHash(["month", "quarter"], "month"), series.monthly_by_nation, _sizes_sql(_S6X, "bucket % 12, (bucket % 12) // 3")),
    ("strata_weekday_hour", strata.CalendarHash(["weekday", "hour"], "hour"), series.hourly_by_type, _sizes_sql(_S1X, "(bucket // 24 + 3) % 7, bucket % 24")),
    ("strata_range6_series", strata.RangeThenSeries(6), series.daily_by_nation, _sizes_sql(_S5X, f"{_RANGE.format(6)}, series_id")),
    ("strata_per_series", strata.PerSeries(), series.monthly_by_nation, _sizes_sql(_S6X, "series_id")),
    ("strata_random_hash", strata.RandomHash(16), series.hourly_by_type, _sizes_sql(_S1X, f"{_BITS} % 16")),
    ("strata_composed", strata.Compose([strata.ModPeriod(7), strata.PerSeries()]), series.hourly_by_type, _sizes_sql(_S1X, "t0 % 7, series_id")),
):
    register(_name, _sizes(_policy, _lagged(_make)), _sql)
_NUM = "numbered AS (SELECT *, row_number() OVER (ORDER BY series_id, t0) - 1 AS num FROM ex), "
_TOTAL = "(SELECT count(*) FROM ex)"
register("strata_cyclic", _sizes(strata.Cyclic(9), _lagged(series.hourly_by_type)), f"WITH {_S1X}, {_NUM}{P.assigned('num % 9', 'numbered')} SELECT stratum, count(*) AS n, round(count(*)::DOUBLE / {_TOTAL}, 9) AS w FROM assigned GROUP BY 1")
register("strata_equal_size", _sizes(strata.EqualSize(11), _lagged(series.hourly_by_type)), f"WITH {_S1X}, {_NUM}{P.assigned(f'num * 11 // {_TOTAL}', 'numbered')} SELECT stratum, count(*) AS n, round(count(*)::DOUBLE / {_TOTAL}, 9) AS w FROM assigned GROUP BY 1")
register(
    "strata_merge_small", _sizes(strata.MergeSmall(strata.WeekdaySeason("year"), 200), _lagged(series.daily_by_region)),
    f"WITH {_S4X}, {P.assigned(f'{_WEEKDAY}, year({_DATE})', 'ex', 'raw')}, big AS (SELECT *, CASE WHEN count(*) OVER (PARTITION BY stratum) < 200 THEN -1 ELSE stratum END AS k FROM raw), "
    f"{P.assigned('k', '(SELECT * EXCLUDE (stratum) FROM big)')} SELECT stratum, count(*) AS n, round(count(*)::DOUBLE / {_TOTAL}, 9) AS w FROM assigned GROUP BY 1",
)
register(
    "strata_finest_count", lambda s, d: strata.Finest().assign(series.lag_examples(series.monthly_by_nation(s, d), 2)).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("stratum").alias("strata"), F.max("stratum").alias("last")),
    f"WITH {_S6X} SELECT count(*) AS n, count(*) AS strata, (count(*) - 1)::BIGINT AS last FROM ex",
)


def strata_feature_bins(spark, d):
    f = series.segment_features(series.segments(series.hourly_by_type(spark, d), 8, 1), ())
    return strata.stratum_table(strata.FeatureBins("density", 5).assign(f)).select(F.col("stratum").cast("long").alias("stratum"), "n", F.round("w", 9).alias("w"))


register(
    "strata_feature_bins", strata_feature_bins,
    f"""WITH {P.S1}, q AS (SELECT series_id, t AS t0, count(*) FILTER (z <> 0) OVER c AS nz, row_number() OVER o AS i, lead(z, 1) OVER o AS e FROM points
 WINDOW o AS (PARTITION BY series_id ORDER BY t), c AS (PARTITION BY series_id ORDER BY t ROWS BETWEEN 7 PRECEDING AND CURRENT ROW)), ex AS (SELECT * FROM q WHERE i >= 8 AND e IS NOT NULL),
 {P.assigned('least(4, floor((nz::DOUBLE / 8) / 0.2))')} SELECT stratum, count(*) AS n, round(count(*)::DOUBLE / {_TOTAL}, 9) AS w FROM assigned GROUP BY 1""",
)


def _clusters(policy, rows):
    return strata.stratum_table(policy.assign(rows)).select(F.col("stratum").cast("long").alias("stratum"), "n", "w")


register("strata_kmeans_embeddings", lambda s, d: _clusters(strata.KMeansPolicy(10, "embedding"), s.read.parquet(f"{d}/embeddings.parquet")))


def strata_kmeans_segments(spark, d):
    f = series.segment_features(series.segments(series.scaled_by_mean(series.hourly_by_type(spark, d)), 72, 24), (24,))
    return _clusters(strata.KMeansPolicy(6), f.select("series_id", "t0", F.array("mean", "std", "density", "autocorr", "spectrum_24").alias("features")))


register("strata_kmeans_segments", strata_kmeans_segments)


def strata_clusters_then_month(spark, d):
    """K-Means clusters of nations by the features of their monthly sales, each split by the month of the forecast."""
    points = series.scaled_by_mean(series.monthly_by_nation(spark, d))
    f = series.segment_features(series.segments(points, 12, 1), (12,)).join(points.select("series_id", F.col("t").alias("t0"), "bucket"), ["series_id", "t0"])
    f = f.select("series_id", "t0", "bucket", F.array("mean", "std").alias("features"))
    return _clusters(strata.Compose([strata.KMeansPolicy(4, level="series"), strata.CalendarHash(["month"], "month")]), f)


register("strata_clusters_then_month", strata_clusters_then_month)


def strata_groups_then_weekday_ranges(spark, d):
    """A given clustering of regions (even and odd keys), then weekday by ten ranges of the span: a part without a key of its own."""
    ex = series.lag_examples(series.daily_by_region(spark, d), 2).withColumn("cluster", F.pmod(F.col("series_id").cast("int"), F.lit(2)))
    found = strata.Compose([strata.GivenStratum("cluster"), strata.WeekdaySeason(10)]).assign(ex)
    return strata.stratum_table(found).select(F.col("stratum").cast("long").alias("stratum"), "n", F.round("w", 9).alias("w"))


register("strata_groups_then_weekday_ranges", strata_groups_then_weekday_ranges, _sizes_sql(_S4X, f"series_id::INTEGER % 2, {_WEEKDAY}, {_RANGE.format(10)}"))

# Draws, from the hourly series by type with weekday strata.


def _placed(spark, d):
    return strata.layout(strata.CalendarHash(["weekday"], "hour").assign(series.lag_examples(series.hourly_by_type(spark, d), 2)))


_PLACED = f"{_S1X}, {P.assigned('(bucket // 24 + 3) % 7')}, {P.LAYOUT}"


def draws_uniform(spark, d):
    placed, table = _placed(spark, d)
    total = placed.count()
    return sampling.uniform_draws(spark, total, 200, 5).join(placed.select("gpos", "series_id", "t0"), "gpos").select("draw", "gpos", "series_id", "t0")


register(
    "draws_uniform", draws_uniform,
    f"WITH {_PLACED}, d AS (SELECT draw, {P.position(sql_uniform(repr('5'), repr('uniform'), 'draw'), _TOTAL)} AS gpos FROM range(200) q(draw)) SELECT d.draw, d.gpos, series_id, t0::BIGINT AS t0 FROM d JOIN placed USING (gpos)",
)


def draws_series_then_time(spark, d):
    index = series.example_index(series.daily_by_supplier(spark, d), 72, 24)
    return sampling.series_then_time_draws(index, 200, 5, correct=True).select("draw", "series_id", "i", F.round("weight", 6).alias("weight"))


register(
    "draws_series_then_time", draws_series_then_time,
    f"""WITH {P.S7}, ix AS (SELECT series_id, n, row_number() OVER (ORDER BY series_id) - 1 AS rank FROM (SELECT series_id, count(*) - 95 AS n FROM points GROUP BY 1) WHERE n > 0), a AS (SELECT count(*) AS s, sum(n) AS total FROM ix),
d AS (SELECT draw, {P.position(sql_uniform(repr('5'), repr('series'), 'draw'), 's')} AS rank, {sql_uniform(repr('5'), repr('time'), 'draw')} AS v, s, total FROM range(200) q(draw), a)
SELECT draw, series_id, {P.position('v', 'n')} AS i, round(s * n / total::DOUBLE, 6) AS weight FROM d JOIN ix USING (rank)""",
)


def draws_stratified(spark, d):
    placed, table = _placed(spark, d)
    return sampling.stratified_draws(table, 4, 5).join(placed.select("stratum", "pos", "series_id", "t0"), ["stratum", "pos"]).select(F.col("stratum").cast("long").alias("stratum"), F.col("draw").cast("long").alias("draw"), "pos", "series_id", "t0", F.round("w", 9).alias("w"))


register(
    "draws_stratified", draws_stratified,
    f"""WITH {_PLACED}, d AS (SELECT stratum, draw, w, {P.position(sql_uniform(repr('5'), repr('stratified'), 'stratum', 'draw'), 'n')} AS pos FROM strata, range(4) q(draw))
SELECT d.stratum, d.draw, d.pos, series_id, t0::BIGINT AS t0, round(d.w, 9) AS w FROM d JOIN placed USING (stratum, pos)""",
)


def draws_without_replacement(spark, d):
    placed, table = _placed(spark, d)
    return sampling.stratified_without_replacement(placed, table, 5, 5).select(F.col("stratum").cast("long").alias("stratum"), F.col("draw").cast("long").alias("draw"), "pos")


register(
    "draws_without_replacement", draws_without_replacement,
    f"WITH {_PLACED}, d AS (SELECT stratum, pos, row_number() OVER (PARTITION BY stratum ORDER BY {sql_uniform(repr('5'), repr('without'), 'stratum', 'pos')}, pos) - 1 AS draw FROM placed) SELECT stratum, draw, pos FROM d WHERE draw < 5",
)


def draws_importance(spark, d):
    placed, _ = _placed(spark, d)
    mass = placed.groupBy("stratum").agg(F.sum("y").alias("mass"))
    return sampling.weighted_draws(mass, 100, 5).select("draw", F.col("stratum").cast("long").alias("stratum"), F.round("weight", 6).alias("weight"))


register(
    "draws_importance", draws_importance,
    f"""WITH {_PLACED}, m AS (SELECT stratum, sum(y) AS mass FROM placed GROUP BY 1), s AS (SELECT stratum, (sum(mass) OVER (ORDER BY stratum) - mass) / sum(mass) OVER () AS lo, sum(mass) OVER (ORDER BY stratum) / sum(mass) OVER () AS hi,
 sum(mass) OVER () / (count(*) OVER () * mass) AS weight FROM m), d AS (SELECT draw, {sql_uniform(repr('5'), repr('weighted'), 'draw')} AS u FROM range(100) q(draw))
SELECT draw, stratum, round(weight, 6) AS weight FROM d JOIN s ON u >= lo AND u < hi""",
)


def geometric_lengths(spark, d):
    """An outer step per day of orders; its inner loop's length is geometric, with the number of the day's strata (priority and status) as mean."""
    days = table(spark, d, "orders").groupBy(day_number(F.col("o_orderdate")).alias("outer")).agg(F.countDistinct(F.struct("o_orderpriority", "o_orderstatus")).alias("strata"))
    return days.select("outer", "strata", sampling.geometric_lengths(F.col("outer"), F.col("strata"), 5).alias("length"))


register(
    "geometric_lengths", geometric_lengths,
    f"""WITH days AS (SELECT {P.DAY.format('o_orderdate')} AS "outer", count(DISTINCT (o_orderpriority, o_orderstatus)) AS strata FROM orders GROUP BY 1)
SELECT "outer", strata, floor(ln(1.0 - {sql_uniform(repr('5'), repr('length'), '"outer"')}) / ln(strata / (strata + 1.0::DOUBLE)))::BIGINT AS length FROM days""",
)


def schedule_rows(spark, d):
    placed, table = _placed(spark, d)
    plan = sampling.build_schedule(spark, [3, 0, 5, 2], table, placed.count(), 2, 3, 5)
    return plan.groupBy("role").agg(F.count(F.lit(1)).alias("n"), F.sum(F.coalesce("pos", "gpos")).alias("positions"))


_ROUNDS = "(VALUES (0, 3), (1, 0), (2, 5), (3, 2)) v(t, length)"
register(
    "schedule_rows", schedule_rows,
    f"""WITH {_PLACED}, a AS (SELECT 'anchor' AS role, {P.position(sql_uniform(repr('5'), repr('anchor'), 't', 'stratum', 'draw'), 'n')} AS p FROM {_ROUNDS}, strata, range(2) q(draw)),
i AS (SELECT 'inner' AS role, {P.position(sql_uniform(repr('5'), repr('inner'), 't', 'k', 'draw'), _TOTAL)} AS p FROM {_ROUNDS}, range(5) g(k), range(3) q(draw) WHERE k < length)
SELECT role, count(*) AS n, sum(p)::BIGINT AS positions FROM (SELECT * FROM a UNION ALL SELECT * FROM i) GROUP BY 1""",
)
