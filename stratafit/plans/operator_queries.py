"""Relational operators and streams in the service of the methods."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.functions.portable import sql_uniform
from stratafit.operators import sampling, series, strata, table_functions
from stratafit.operators.gradients import with_gradient
from stratafit.plans import sql_parts as P
from stratafit.plans.catalogue import register
from stratafit.plans.training_queries import THETA, nation_examples
from stratafit.sources.tables import cents, hour_number, table
from stratafit.streaming import feeds

_S6X = f"{P.S6}, {P.SCALED}, {P.examples()}"
_YEARS = f"{_S6X}, {P.gradients(THETA, 'ex')}, q AS (SELECT *, (bucket // 12) + 1970 AS year FROM grads)"


def _losses(spark, d):
    return with_gradient(nation_examples(spark, d), THETA).withColumn("year", (F.floor(F.col("bucket") / 12) + 1970).cast("long"))


def _grouped(kind):
    def query(spark, d):
        g = getattr(_losses(spark, d), kind)("series_id", "year")
        return g.agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"), F.round(F.avg("loss"), 6).alias("loss"))

    return query


for _kind in ("cube", "rollup"):
    register(f"loss_{_kind}", _grouped(_kind), f"WITH {_YEARS} SELECT series_id, year::BIGINT AS year, grouping_id(series_id, year)::BIGINT AS level, count(*) AS n, round(avg(loss), 6) AS loss FROM q GROUP BY {_kind.upper()} (series_id, year)")


def loss_grouping_sets(spark, d):
    sets = _losses(spark, d).groupingSets([["series_id"], ["year"], []], "series_id", "year")
    return sets.agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"), F.round(F.avg("loss"), 6).alias("loss"))


register("loss_grouping_sets", loss_grouping_sets,
         f"WITH {_YEARS} SELECT series_id, year::BIGINT AS year, grouping_id(series_id, year)::BIGINT AS level, count(*) AS n, round(avg(loss), 6) AS loss FROM q GROUP BY GROUPING SETS ((series_id), (year), ())")


def top_segments_lateral(spark, d):
    """Each nation's two examples of largest loss, by a lateral subquery."""
    losses = _losses(spark, d)
    names = losses.select(F.col("series_id").alias("nation")).distinct()
    best = losses.filter(F.col("series_id") == F.col("nation").outer()).orderBy(F.col("loss").desc(), "t0").limit(2).select("t0", F.round("loss", 6).alias("worst"))
    return names.lateralJoin(best).select(F.col("nation").alias("series_id"), "t0", F.col("worst").alias("loss"))


register("top_segments_lateral", top_segments_lateral,
         f"WITH {_S6X}, {P.gradients(THETA, 'ex')}, k AS (SELECT *, row_number() OVER (PARTITION BY series_id ORDER BY loss DESC, t0) AS i FROM grads) SELECT series_id, t0::BIGINT AS t0, round(loss, 6) AS loss FROM k WHERE i <= 2")


def worst_strata_topk(spark, d):
    """The three nations of largest mean loss in each quarter of the year."""
    q = _losses(spark, d).withColumn("quarter", F.floor(F.pmod(F.col("bucket"), F.lit(12)) / 3) + 1)
    per = q.groupBy("quarter", "series_id").agg(F.avg("loss").alias("mean"))
    rank = F.row_number().over(W.Window.partitionBy("quarter").orderBy(F.col("mean").desc(), "series_id"))
    return per.withColumn("rank", rank).filter("rank <= 3").select(F.col("quarter").cast("long").alias("quarter"), "rank", "series_id", F.round("mean", 6).alias("loss"))


register("worst_strata_topk", worst_strata_topk,
         f"""WITH {_S6X}, {P.gradients(THETA, 'ex')}, p AS (SELECT (bucket % 12) // 3 + 1 AS quarter, series_id, avg(loss) AS mean FROM grads GROUP BY 1, 2), k AS (SELECT *, row_number() OVER (PARTITION BY quarter ORDER BY mean DESC, series_id) AS rank FROM p)
SELECT quarter::BIGINT AS quarter, rank::INTEGER AS rank, series_id, round(mean, 6) AS loss FROM k WHERE rank <= 3""")  # fmt: skip


def asof_fill(spark, d):
    """For each purchase the user's last view at or before it: a union in time order and the last value carried on, no range join."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", "ts", cents(F.col("value")).alias("v")).filter("event_type in ('view', 'purchase') and user_id is not null")
    order = W.Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.Window.unboundedPreceding, 0)
    seen = e.withColumn("view_cents", F.last(F.when(F.col("event_type") == "view", F.col("v")), ignorenulls=True).over(order))
    return seen.filter("event_type = 'purchase'").select("event_id", "user_id", "view_cents")


register("asof_fill", asof_fill,
         f"""WITH e AS (SELECT event_id, user_id, event_type, ts, {P.cents('value')} AS v FROM events WHERE event_type IN ('view', 'purchase') AND user_id IS NOT NULL),
s AS (SELECT *, last_value(CASE WHEN event_type = 'view' THEN v END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS view_cents FROM e) SELECT event_id, user_id, view_cents FROM s WHERE event_type = 'purchase'""")  # fmt: skip


def interval_join_events(spark, d):
    """Per type pair, how many events of a user follow another within an hour: equi-join on user and hour bucket, twice, then the interval."""
    e = table(spark, d, "events").filter("user_id is not null").select("event_id", "user_id", "event_type", "ts", hour_number(F.col("ts")).alias("h"))
    a = e.select(F.col("event_id").alias("a_id"), "user_id", F.col("event_type").alias("first"), F.col("ts").alias("a_ts"), F.explode(F.array(F.col("h"), F.col("h") + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("b_id"), "user_id", F.col("event_type").alias("second"), F.col("ts").alias("b_ts"), "h")
    within = (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr("interval 1 hour"))
    return a.join(b, ["user_id", "h"]).filter(within).groupBy("first", "second").agg(F.count(F.lit(1)).alias("n"))


register("interval_join_events", interval_join_events,
         'SELECT a.event_type AS "first", b.event_type AS "second", count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY 1, 2')


def _drawn(spark, d):
    placed, info = strata.layout(strata.PerSeries().assign(nation_examples(spark, d)))
    return placed, sampling.stratified_draws(info, 3, 31)


def undrawn_examples_anti(spark, d):
    placed, draws = _drawn(spark, d)
    left = placed.join(draws.select("stratum", "pos").distinct(), ["stratum", "pos"], "left_anti")
    return left.groupBy("series_id").agg(F.count(F.lit(1)).alias("n"))


_DRAWN = f"{_S6X}, {P.assigned('series_id')}, {P.LAYOUT}, d AS (SELECT stratum, {P.position(sql_uniform(repr('31'), repr('stratified'), 'stratum', 'draw'), 'n')} AS pos FROM strata, range(3) q(draw))"
register("undrawn_examples_anti", undrawn_examples_anti, f"WITH {_DRAWN} SELECT series_id, count(*) AS n FROM placed WHERE NOT EXISTS (SELECT 1 FROM d WHERE d.stratum = placed.stratum AND d.pos = placed.pos) GROUP BY 1")


def drawn_examples_semi(spark, d):
    placed, draws = _drawn(spark, d)
    return placed.join(draws, ["stratum", "pos"], "left_semi").groupBy("series_id").agg(F.count(F.lit(1)).alias("n"))


register("drawn_examples_semi", drawn_examples_semi, f"WITH {_DRAWN} SELECT series_id, count(*) AS n FROM placed WHERE EXISTS (SELECT 1 FROM d WHERE d.stratum = placed.stratum AND d.pos = placed.pos) GROUP BY 1")


def train_test_disjoint(spark, d):
    """Targets of training and test examples share no tick, and together are all targets."""
    train, test = series.split_by_time(series.hourly_by_type(spark, d), 600, 8)
    targets = lambda p: series.lag_examples(p, 8).select("series_id", "t0")
    both, every = targets(train).intersect(targets(test)), targets(series.hourly_by_type(spark, d))
    missing = every.exceptAll(targets(train).unionByName(targets(test)))
    return both.agg(F.count(F.lit(1)).alias("shared")).join(missing.agg(F.count(F.lit(1)).alias("missing")))


register("train_test_disjoint", train_test_disjoint, "SELECT 0::BIGINT AS shared, 0::BIGINT AS missing")


#: All event types of the tables. Fixed values.
EVENT_TYPES = ("cart", "click", "purchase", "search", "view")


def pivot_vector_series(spark, d):
    p = series.hourly_by_type(spark, d)
    return p.groupBy("t").pivot("series_id", list(EVENT_TYPES)).agg(F.first("z")).select("t", *[F.col(c).cast("long").alias(c) for c in EVENT_TYPES])


register("pivot_vector_series", pivot_vector_series,
         f"WITH {P.S1} SELECT t::BIGINT AS t, " + ", ".join(f"max(z) FILTER (series_id = '{c}')::BIGINT AS {c}" for c in EVENT_TYPES) + " FROM points GROUP BY 1")


def dynamic_covariate(spark, d):
    """A covariate out of JSON: mean of props.k by type and weekday."""
    e = table(spark, d, "events").select("event_type", F.get_json_object("props", "$.k").cast("long").alias("k"), F.weekday("ts").alias("weekday"))
    return e.groupBy("event_type", "weekday").agg(F.round(F.avg("k"), 6).alias("mean_k"), F.count_if(F.col("k").isNull()).alias("missing"))


register("dynamic_covariate", dynamic_covariate,
         "SELECT event_type, (isodow(ts) - 1)::INTEGER AS weekday, round(avg((props->>'$.k')::BIGINT), 6) AS mean_k, count(*) FILTER ((props->>'$.k') IS NULL) AS missing FROM events GROUP BY 1, 2")


def segments_table_function(spark, d):
    """The SQL table function over the monthly nation series."""
    table_functions.register(spark)
    view = f"points_{uuid.uuid4().hex}"
    series.monthly_by_nation(spark, d).createOrReplaceTempView(view)
    s = spark.sql(f"SELECT * FROM segments(TABLE({view}) PARTITION BY series_id ORDER BY (t), 6, 2)")
    return s.select("series_id", "t0", F.aggregate("context", F.lit(0.0), lambda a, x: a + x).cast("long").alias("context_sum"), F.col("target")[1].cast("long").alias("last"))


register("segments_table_function", segments_table_function,
         f"""WITH {P.S6}, q AS (SELECT series_id, t AS t0, sum(z) OVER (PARTITION BY series_id ORDER BY t ROWS BETWEEN 5 PRECEDING AND CURRENT ROW) AS c, lead(z, 2) OVER (PARTITION BY series_id ORDER BY t) AS l, row_number() OVER (PARTITION BY series_id ORDER BY t) AS i FROM points)
SELECT series_id, t0::BIGINT AS t0, c::BIGINT AS context_sum, l::BIGINT AS last FROM q WHERE i >= 6 AND l IS NOT NULL""")  # fmt: skip

# Streams.


def _name(kind):
    return f"{kind}_{uuid.uuid4().hex}"


def stream_hourly_series(spark, d):
    out = feeds.run_once(feeds.hourly_cents(feeds.events_stream(spark, d)), _name("hourly"), "complete")
    return out.select(hour_number(F.col("start")).alias("bucket"), "series_id", "z_cents")


register("stream_hourly_series", stream_hourly_series, f"SELECT {P.HOUR.format('ts')}::BIGINT AS bucket, event_type AS series_id, sum({P.cents('value')})::BIGINT AS z_cents FROM events GROUP BY 1, 2")


def stream_stratum_counts(spark, d):
    stratum = F.weekday("ts") * 24 + F.hour("ts")
    return feeds.run_once(feeds.stratum_counts(feeds.events_stream(spark, d), stratum), _name("strata"), "complete")


register("stream_stratum_counts", stream_stratum_counts, "SELECT ((isodow(ts) - 1) * 24 + hour(ts))::INTEGER AS stratum, count(*) AS n FROM events GROUP BY 1")


def stream_segments(spark, d):
    """Events as they come, of each type in order of their id, cut by the stateful segmenter."""
    points = feeds.events_stream(spark, d).select(F.col("event_type").alias("series_id"), F.col("event_id").alias("t"), cents(F.col("value")).cast("double").alias("z"))
    out = feeds.run_once(feeds.segment_stream(points, 3, 1), _name("segments"))
    return out.select("series_id", "t0", F.aggregate("context", F.lit(0.0), lambda a, x: a + x).cast("long").alias("context_sum"), F.col("target")[0].cast("long").alias("target"))


register("stream_segments", stream_segments,
         f"""WITH p AS (SELECT event_type AS series_id, event_id AS t, {P.cents('value')} AS z FROM events), q AS (SELECT series_id, t - 1 AS t0, sum(z) OVER (PARTITION BY series_id ORDER BY t ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING) AS c, z,
 row_number() OVER (PARTITION BY series_id ORDER BY t) AS i FROM p) SELECT series_id, t0::BIGINT AS t0, c::BIGINT AS context_sum, z::BIGINT AS target FROM q WHERE i >= 4""")  # fmt: skip


def stream_reservoirs(spark, d):
    """Ten events a weekday, sampled while they stream; the stratum is the key of the batch policy."""
    stratum = strata.CalendarHash(["weekday"], "hour").key().getField("weekday")
    events = feeds.events_stream(spark, d).withColumn("bucket", hour_number(F.col("ts")))
    rows = feeds.run_once(feeds.reservoirs(events, stratum, 10, "event_id"), _name("reservoirs"))
    first = F.row_number().over(W.Window.partitionBy("stratum").orderBy("u"))
    return rows.withColumn("place", first).filter(F.col("place") <= 10).select("stratum", "place", "key")


_PICK = "(('0x' || substr(md5(concat_ws('|', '3', 'reservoir', event_id)), 1, 13))::BIGINT)"
register("stream_reservoirs", stream_reservoirs,
         f"SELECT * FROM (SELECT (isodow(ts) - 1)::INTEGER AS stratum, row_number() OVER (PARTITION BY isodow(ts) ORDER BY {_PICK})::INTEGER AS place, event_id AS key FROM events) WHERE place <= 10")


def statistics_by_nation(spark, d):
    """Covariance, correlation and regression of a month's sales on the month before, by nation."""
    ex = nation_examples(spark, d)
    stats = {"covariance": F.covar_pop("y", "x1"), "spread": F.covar_samp("y", "x1"), "correlation": F.corr("y", "x1"), "slope": F.regr_slope("y", "x1"), "intercept": F.regr_intercept("y", "x1"), "fit": F.regr_r2("y", "x1"), "middle": F.percentile("y", F.lit(0.5))}
    return ex.groupBy("series_id").agg(*[F.round(f, 6).alias(name) for name, f in stats.items()], F.count_if(F.col("y") > F.col("x1")).alias("rises"))


register("statistics_by_nation", statistics_by_nation,
         f"""WITH {_S6X} SELECT series_id, round(covar_pop(y, x1), 6) AS covariance, round(covar_samp(y, x1), 6) AS spread, round(corr(y, x1), 6) AS correlation, round(regr_slope(y, x1), 6) AS slope, round(regr_intercept(y, x1), 6) AS intercept,
 round(regr_r2(y, x1), 6) AS fit, round(quantile_cont(y, 0.5), 6) AS middle, count(*) FILTER (y > x1) AS rises FROM ex GROUP BY 1""")  # fmt: skip


def join_strategies(spark, d):
    """Revenue by nation through each physical join: the hint changes the plan, not the rows."""
    li = table(spark, d, "lineitem").select("l_suppkey", cents(F.col("l_extendedprice")).alias("z"))
    suppliers = table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    out = None
    for hint in ("broadcast", "merge", "shuffle_hash"):
        one = li.join(suppliers.hint(hint), "l_suppkey").groupBy(F.lit(hint).alias("strategy"), "s_nationkey").agg(F.count(F.lit(1)).alias("n"), F.sum("z").alias("cents"))
        out = one if out is None else out.unionByName(one)
    return out


register("join_strategies", join_strategies,
         f"SELECT strategy, s_nationkey, count(*) AS n, sum({P.cents('l_extendedprice')})::BIGINT AS cents FROM lineitem JOIN supplier ON s_suppkey = l_suppkey, (VALUES ('broadcast'), ('merge'), ('shuffle_hash')) v(strategy) GROUP BY 1, 2")
