"""Gradients, losses, variances, fits and theory."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.functions import losses
from stratafit.functions.portable import py_uniform, sql_normal, sql_uniform
from stratafit.models.arrow_kernel import evaluate
from stratafit.models.forecasters import LSTMModel, MLPModel, ResidualStackModel, mse_loss
from stratafit.operators import gradients, measures, sampling, series, strata
from stratafit.optim import loop
from stratafit.optim.problems import MomentsProblem, SegmentProblem
from stratafit.operators.prepared import prepared
from stratafit.optim.rules import make_rule
from stratafit.plans import sql_parts as P
from stratafit.plans.catalogue import register
from stratafit.sources import synthetic, tables
from stratafit.theory.checks import complexity_table

THETA = (0.3, 0.2)
ZERO = (0.0, 0.0)


def nation_examples(spark, d):
    """Monthly sales by nation on a common scale, order 2."""
    return series.lag_examples(series.scaled_by_mean(series.monthly_by_nation(spark, d)), 2)


def carrier_examples(spark, d):
    return series.lag_examples(synthetic.carrier(series.hourly_by_type(spark, d)), 2)


def toy_examples(spark, d, step=math.pi / 4):
    return series.lag_examples(synthetic.toy(spark, 4000, step), 2)


def event_toy_examples(spark, d, step=math.pi / 4):
    """The toy's season on the hourly events of each type."""
    return series.lag_examples(synthetic.toy_on(series.hourly_by_type(spark, d), step), 2)


_S6X = f"{P.S6}, {P.SCALED}, {P.examples()}"
_BY_NATION = f"{_S6X}, {P.assigned('series_id')}"
_PLACED = f"{_BY_NATION}, {P.LAYOUT}"


def _toy_points(step: float) -> str:
    return f"toy AS (SELECT 'toy' AS series_id, id AS t, id AS bucket, sin(id * {step!r}) + cos(id * {step!r} * 2) + 0.2 * {sql_normal(repr('1'), repr('toy'), 'id')} AS z FROM range(4000) q(id))"


_TOYX = f"{_toy_points(math.pi / 4)}, {P.examples('toy')}"
_STATS = "st AS (SELECT series_id, avg(z::DOUBLE) AS m, stddev_pop(z::DOUBLE) AS s FROM points GROUP BY 1)"


def _event_toy(step: float) -> str:
    return f"{P.S1}, {_STATS}, toy AS (SELECT series_id, t, bucket, sin(t * {step!r}) + cos(t * {step!r} * 2) + 0.2 * (z - m) / s AS z FROM points JOIN st USING (series_id)), {P.examples('toy')}"


_CARRIERX = f"""{P.S1}, {_STATS},
carried AS (SELECT series_id, t, bucket, 2.0 * sin((bucket % 24) * {2 * math.pi / 24!r}) + cos((bucket % 24) * {2 * math.pi / 6!r}) + 0.2 * (z - m) / s AS z FROM points JOIN st USING (series_id)), {P.examples('carried')}"""


def _r(*cols, digits=6):
    return [F.round(c, digits).alias(c) for c in cols]


# Gradients at fixed parameters.
register("ar_loss", lambda s, d: gradients.with_gradient(nation_examples(s, d), THETA).groupBy("series_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("loss"), 6).alias("loss")),
         f"WITH {_S6X}, {P.gradients(THETA, 'ex')} SELECT series_id, count(*) AS n, round(avg(loss), 6) AS loss FROM grads GROUP BY 1")
register("ar_full_gradient", lambda s, d: gradients.full_gradient(nation_examples(s, d), THETA).select("n", *_r("loss", "g1", "g2")),
         f"WITH {_S6X}, {P.gradients(THETA, 'ex')} SELECT count(*) AS n, round(avg(loss), 6) AS loss, round(avg(g1), 6) AS g1, round(avg(g2), 6) AS g2 FROM grads")


def ar_minibatch_gradient(spark, d):
    placed, _ = strata.layout(strata.PerSeries().assign(nation_examples(spark, d)))
    draws = sampling.uniform_draws(spark, placed.count(), 64, 9)
    return gradients.full_gradient(placed.join(draws, "gpos"), THETA).select("n", *_r("loss", "g1", "g2"))


_MINI = f"d AS (SELECT {P.position(sql_uniform(repr('9'), repr('uniform'), 'draw'), '(SELECT count(*) FROM ex)')} AS gpos FROM range(64) q(draw)), mini AS (SELECT placed.* FROM d JOIN placed USING (gpos))"
register("ar_minibatch_gradient", ar_minibatch_gradient,
         f"WITH {_PLACED}, {_MINI}, {P.gradients(THETA, 'mini')} SELECT count(*) AS n, round(avg(loss), 6) AS loss, round(avg(g1), 6) AS g1, round(avg(g2), 6) AS g2 FROM grads")


def ar_stratified_gradient(spark, d):
    placed, table = strata.layout(strata.PerSeries().assign(nation_examples(spark, d)))
    return gradients.stratified_gradient(placed, sampling.stratified_draws(table, 2, 9), THETA).select(*_r("g1", "g2"))


_STRAT = f"d AS (SELECT stratum, w, {P.position(sql_uniform(repr('9'), repr('stratified'), 'stratum', 'draw'), 'n')} AS pos FROM strata, range(2) q(draw)), drawn AS (SELECT placed.*, d.w FROM d JOIN placed USING (stratum, pos))"
register("ar_stratified_gradient", ar_stratified_gradient,
         f"WITH {_PLACED}, {_STRAT}, {P.gradients(THETA, 'drawn')} SELECT round(sum(w * a), 6) AS g1, round(sum(w * b), 6) AS g2 FROM (SELECT stratum, w, avg(g1) AS a, avg(g2) AS b FROM grads GROUP BY 1, 2)")


def ar_control_variate_step(spark, d):
    """One inner direction at THETA with the anchor taken at 0: minibatch gradient here, less there, plus the stratified anchor."""
    placed, table = strata.layout(strata.PerSeries().assign(nation_examples(spark, d)))
    mini = placed.join(sampling.uniform_draws(spark, placed.count(), 64, 9), "gpos")
    here = gradients.full_gradient(mini, THETA).select(F.col("g1").alias("h1"), F.col("g2").alias("h2"))
    there = gradients.full_gradient(mini, ZERO).select(F.col("g1").alias("t1"), F.col("g2").alias("t2"))
    anchor = gradients.stratified_gradient(placed, sampling.stratified_draws(table, 2, 9), ZERO)
    return here.join(there).join(anchor).select(F.round(F.expr("h1 - t1 + g1"), 6).alias("v1"), F.round(F.expr("h2 - t2 + g2"), 6).alias("v2"))


register("ar_control_variate_step", ar_control_variate_step,
         f"""WITH {_PLACED}, {_MINI}, {_STRAT.replace('d AS (SELECT stratum', 'sd AS (SELECT stratum', 1).replace('FROM d JOIN', 'FROM sd JOIN').replace('placed.*, d.w', 'placed.*, sd.w')}, {P.gradients(THETA, 'mini', 'gh')}, {P.gradients(ZERO, 'mini', 'gt')}, {P.gradients(ZERO, 'drawn', 'ga')},
a AS (SELECT sum(w * a) AS g1, sum(w * b) AS g2 FROM (SELECT stratum, w, avg(g1) AS a, avg(g2) AS b FROM ga GROUP BY 1, 2))
SELECT round((SELECT avg(g1) FROM gh) - (SELECT avg(g1) FROM gt) + a.g1, 6) AS v1, round((SELECT avg(g2) FROM gh) - (SELECT avg(g2) FROM gt) + a.g2, 6) AS v2 FROM a""")  # fmt: skip
_TYPES = ("cart", "click", "purchase", "search", "view")


def var_full_gradient(spark, d):
    """Vector autoregression of order 1 over the five regions' daily sales, at parameters 0.1 everywhere."""
    points = series.scaled_by_mean(series.daily_by_region(spark, d))
    ex = gradients.vector_examples(points, 1, [str(k) for k in range(5)])
    return gradients.var_full_gradient(ex, 1, 5, np.full((5, 5, 1), 0.1)).select("output", "series", "lag", F.round("g", 6).alias("g"))


register("var_full_gradient", var_full_gradient,
         f"""WITH {P.S4}, {P.SCALED}, l AS (SELECT series_id::INTEGER AS k, t, z AS y, lag(z) OVER (PARTITION BY series_id ORDER BY t) AS x FROM scaled), s AS (SELECT t, sum(x) AS total FROM l WHERE x IS NOT NULL GROUP BY 1)
SELECT o.k AS output, i.k AS series, 1 AS lag, round(avg(2.0 * (0.1 * s.total - o.y) * i.x), 6) AS g FROM l o JOIN l i ON i.t = o.t JOIN s ON s.t = o.t WHERE o.x IS NOT NULL GROUP BY 1, 2""")  # fmt: skip

# Losses of simple forecasters: persistence (x1) and the mean of the last two.


def _loss(name, expr, sql):
    register(name, lambda s, d: nation_examples(s, d).groupBy("series_id").agg(F.round(F.avg(expr(F.col("y"), F.col("x1"), F.col("x2"))), 6).alias("loss")), f"WITH {_S6X} SELECT series_id, round(avg({sql}), 6) AS loss FROM ex GROUP BY 1")


_loss("loss_mse", lambda y, x1, x2: losses.mse(y, x1), "(x1 - y) * (x1 - y)")
_loss("loss_gaussian_nll", lambda y, x1, x2: losses.gaussian_nll(y, (x1 + x2) / 2, F.lit(0.7)), f"{0.5 * math.log(2 * math.pi)!r} + ln(0.7) + 0.5 * ((y - (x1 + x2) / 2) / 0.7) * ((y - (x1 + x2) / 2) / 0.7)")
_T5 = math.lgamma(2.5) - math.lgamma(3.0) + 0.5 * math.log(5 * math.pi)
_loss("loss_student_nll", lambda y, x1, x2: losses.student_nll(y, x1, F.lit(0.7), 5.0), f"{_T5!r} + ln(0.7) + 3.0 * ln(1.0 + ((y - x1) / 0.7) * ((y - x1) / 0.7) / 5.0)")
_loss("loss_mape", lambda y, x1, x2: losses.mape(y, x1), "abs(x1 - y) / nullif(abs(y), 0.0)")
_loss("loss_pinball", lambda y, x1, x2: losses.pinball(y, x1, 0.9), "greatest(0.9 * (y - x1), (0.9 - 1) * (y - x1))")


def loss_kl(spark, d):
    """Divergence of each nation's later half from its earlier half, both taken as normal."""
    p = series.scaled_by_mean(series.monthly_by_nation(spark, d))
    half = lambda c, n: p.filter(c).groupBy("series_id").agg(F.avg("z").alias(f"m{n}"), F.stddev_pop("z").alias(f"s{n}"))
    both = half(F.col("t") >= 42, 1).join(half(F.col("t") < 42, 0), "series_id").filter("s1 > 0 and s0 > 0")
    return both.select("series_id", F.round(losses.kl_gaussian(F.col("m1"), F.col("s1"), F.col("m0"), F.col("s0")), 6).alias("kl"))


register("loss_kl", loss_kl, f"""WITH {P.S6}, {P.SCALED}, h AS (SELECT series_id, avg(z) FILTER (t >= 42) AS m1, stddev_pop(z) FILTER (t >= 42) AS s1, avg(z) FILTER (t < 42) AS m0, stddev_pop(z) FILTER (t < 42) AS s0 FROM scaled GROUP BY 1)
SELECT series_id, round(ln(s0 / s1) + (s1 * s1 + (m1 - m0) * (m1 - m0)) / (2.0 * s0 * s0) - 0.5, 6) AS kl FROM h WHERE s1 > 0 AND s0 > 0""")  # fmt: skip

# Variance.
register("gradient_variance", lambda s, d: measures.gradient_variance(nation_examples(s, d), ZERO, 4).select("n", *_r("variance")),
         f"WITH {_S6X}, {P.gradients(ZERO, 'ex')} SELECT count(*) AS n, round((var_pop(g1) + var_pop(g2)) / 4, 6) AS variance FROM grads")
register("stratum_variance", lambda s, d: measures.stratum_variance(strata.PerSeries().assign(nation_examples(s, d)), ZERO).select(F.col("stratum").cast("long").alias("stratum"), "n", *_r("w", "variance")),
         f"WITH {_BY_NATION}, {P.gradients(ZERO)} SELECT stratum, count(*) AS n, round(count(*)::DOUBLE / (SELECT count(*) FROM ex), 6) AS w, round(var_pop(g1) + var_pop(g2), 6) AS variance FROM grads GROUP BY 1")
_DEP = ("total", "within", "between", "stratified", "dependency", "mean_inside", "within_share")


def _dep_sql(with_part, theta=ZERO):
    return f"""WITH {with_part}, {P.gradients(theta)}, dep AS ({P.dependency()}) SELECT strata, round(total, 6) AS total, round(within, 6) AS within, round(total - within, 6) AS between, round(stratified, 6) AS stratified,
 round(strata * stratified, 6) AS dependency, round(mean_inside, 6) AS mean_inside, round(within / nullif(total, 0), 6) AS within_share, strata * stratified > total AS worse FROM dep"""


register("stratified_variance", lambda s, d: measures.variance_dependency(strata.PerSeries().assign(nation_examples(s, d)), THETA, 1).select("strata", *_r("stratified")),
         f"SELECT strata, stratified FROM ({_dep_sql(_BY_NATION, THETA)})")
register("variance_dependency", lambda s, d: measures.variance_dependency(strata.PerSeries().assign(nation_examples(s, d)), ZERO).select("strata", *_r(*_DEP), "worse"), _dep_sql(_BY_NATION))
register("toy_variance", lambda s, d: measures.variance_dependency(strata.ModPeriod(8).assign(event_toy_examples(s, d)), ZERO).select("strata", *_r(*_DEP), "worse"), _dep_sql(f"{_event_toy(math.pi / 4)}, {P.assigned('t0 % 8')}"))
register("toy_variance_wrong_step", lambda s, d: measures.variance_dependency(strata.ModPeriod(8).assign(event_toy_examples(s, d, 1.0)), ZERO).select("strata", *_r(*_DEP), "worse"),
         _dep_sql(f"{_event_toy(1.0)}, {P.assigned('t0 % 8')}"))
_HOURS, _WEEK = strata.CalendarHash(["hour"], "hour"), strata.CalendarHash(["weekday"], "hour")
_PARTS = (
    ("nations", nation_examples, {"per_series": strata.PerSeries(), "month": strata.CalendarHash(["month"], "month")}, _S6X, {"per_series": "series_id", "month": "bucket % 12"}),
    ("carrier", carrier_examples, {"hour": _HOURS, "weekday": _WEEK}, _CARRIERX, {"hour": "bucket % 24", "weekday": "(bucket // 24 + 3) % 7"}),
    ("toy", toy_examples, {"mod8": strata.ModPeriod(8)}, _TOYX, {"mod8": "t0 % 8"}),
)


def policy_comparison(spark, d):
    out = None
    for name, make, policies, _, _ in _PARTS:
        one = measures.policy_comparison(make(spark, d), policies, ZERO).select(F.lit(name).alias("workload"), "policy", "strata", *_r("total", "within_share", "dependency", "random_share"))
        out = one if out is None else out.unionByName(one)
    return out


def _comparison_sql(workload, with_part, policy, key):
    bits = "(('0x' || substr(md5(concat_ws('|', '3', 'relabel', series_id, t0)), 1, 13))::BIGINT)"
    return f"""(WITH {with_part}, {P.assigned(key)}, {P.gradients(ZERO)}, dep AS ({P.dependency()}), sz AS (SELECT stratum, count(*) AS n FROM assigned GROUP BY 1), ends AS (SELECT stratum, sum(n) OVER (ORDER BY stratum) - n AS lo, n FROM sz),
mixed AS (SELECT * EXCLUDE (stratum), row_number() OVER (ORDER BY {bits}, series_id, t0) - 1 AS r0 FROM assigned), relabel AS (SELECT mixed.*, stratum FROM mixed JOIN ends ON r0 >= lo AND r0 < lo + n), {P.gradients(ZERO, 'relabel', 'gr')}, rd AS ({P.dependency('gr')})
SELECT '{workload}' AS workload, '{policy}' AS policy, dep.strata, round(dep.total, 6) AS total, round(dep.within / dep.total, 6) AS within_share, round(dep.strata * dep.stratified, 6) AS dependency, round(rd.within / rd.total, 6) AS random_share FROM dep, rd)"""


register("policy_comparison", policy_comparison, " UNION ALL ".join(_comparison_sql(w, sql, p, key) for w, _, _, sql, keys in _PARTS for p, key in keys.items()))


def sampler_variance(spark, d):
    return measures.sampler_variance(strata.ModPeriod(8).assign(event_toy_examples(spark, d)), ZERO, 100, 1, 13).select("sampler", "draws", *_r("empirical"))


register("sampler_variance", sampler_variance,
         f"""WITH {_event_toy(math.pi / 4)}, {P.assigned('t0 % 8')}, {P.LAYOUT}, {P.gradients(ZERO, 'placed')}, m AS (SELECT avg(g1) AS m1, avg(g2) AS m2 FROM grads),
sd AS (SELECT rep, stratum, w, floor({sql_uniform(repr('13'), repr('rep'), 'rep', 'stratum', '0')} * n)::BIGINT AS pos FROM range(100) q(rep), strata),
s AS (SELECT 'stratified' AS sampler, rep, sum(w * g1) AS g1, sum(w * g2) AS g2 FROM sd JOIN grads USING (stratum, pos) GROUP BY 2),
ud AS (SELECT rep, floor({sql_uniform(repr('13'), repr('rep'), 'rep', repr('u'), 'draw')} * (SELECT count(*) FROM ex))::BIGINT AS gpos FROM range(100) q(rep), range(8) k(draw)),
u AS (SELECT 'uniform' AS sampler, rep, avg(g1) AS g1, avg(g2) AS g2 FROM ud JOIN grads USING (gpos) GROUP BY 2)
SELECT sampler, 8::BIGINT AS draws, round(avg((g1 - m1) * (g1 - m1) + (g2 - m2) * (g2 - m2)), 6) AS empirical FROM (SELECT * FROM s UNION ALL SELECT * FROM u), m GROUP BY 1""")  # fmt: skip

# Fits: 20 updates at most, on the nation series.
SEED, LR = 21, {"sgd": 0.003, "momentum": 0.001, "rmsprop": 0.02, "adam": 0.03, "adagrad": 0.05}
_GEOMETRIC = sampling.inner_lengths(6, 5, SEED, cap=5)
_SOURCES = {  # kind: (schedule's anchor, lengths of inner loops)
    "minibatch": ("none", [20]), "stratified": ("stratified", [1] * 12), "anchored": ("stratified", _GEOMETRIC), "anchored_fixed": ("stratified", [4] * 5), "batch": ("batch", _GEOMETRIC), "full": ("full", _GEOMETRIC), "hashed": ("stratified", _GEOMETRIC),
    "descent": ("full", [1] * 12),
}
FITS = {
    "fit_sgd": ("minibatch", "sgd", None), "fit_momentum": ("minibatch", "momentum", None), "fit_rmsprop": ("minibatch", "rmsprop", None), "fit_adam": ("minibatch", "adam", None), "fit_adagrad": ("minibatch", "adagrad", None),
    "fit_stratified": ("stratified", "sgd", None), "fit_batch_anchor": ("batch", "sgd", None), "fit_hashed_anchor": ("hashed", "sgd", None), "fit_full_anchor": ("full", "sgd", None), "fit_full_descent": ("descent", "sgd", None), "fit_anchored": ("anchored", "sgd", None), "fit_anchored_fixed": ("anchored_fixed", "sgd", None),
    "fit_anchored_gamma": ("anchored_fixed", "sgd", 0.7), "fit_anchored_adam": ("anchored", "adam", None), "fit_anchored_adagrad": ("anchored", "adagrad", None),
}
_BATCH = 25


def run_fit(spark, d, name):
    kind, rule_name, gamma = FITS[name]
    anchor, lengths = _SOURCES[kind]
    placed, table = strata.layout((strata.RandomHash(16, 7) if kind == "hashed" else strata.PerSeries()).assign(nation_examples(spark, d)))
    placed = prepared(placed.select("stratum", "pos", "gpos", "y", "x1", "x2"))
    full = gradients.moments(placed, [], 2).first().asDict()
    schedule = sampling.build_schedule(spark, lengths, table, full["n"], 1, 2, SEED, anchor, _BATCH)
    problem = MomentsProblem.collect(placed, table, schedule, 2, full if anchor == "full" else None, weighted=anchor == "stratified")
    rule = make_rule(rule_name, LR[rule_name])
    if kind == "minibatch":
        return loop.minibatch_fit(problem, rule, [(0, k) for k in range(lengths[0])], method=name)
    if kind == "stratified":
        return loop.stratified_fit(problem, rule, len(lengths), method=name)
    return loop.anchored_fit(problem, rule, lengths, gamma=gamma, method=name)


def _fit_query(name):
    def query(spark, d):
        trace = run_fit(spark, d, name).trace.to_df(spark)
        return trace.select("method", "outer", "inner", F.round(F.col("theta")[0], 6).alias("theta1"), F.round(F.col("theta")[1], 6).alias("theta2"))

    return query


def _fit_sql(name):
    kind, rule, gamma = FITS[name]
    anchor, lengths = _SOURCES[kind]
    lr = LR[rule]
    steps = [(t, k) for t, n in enumerate(lengths) for k in range(n)]
    seq = "seq(s, o, k) AS (VALUES " + ", ".join(f"({i + 1}, {t}, {k})" for i, (t, k) in enumerate(steps)) + ")"
    rounds = "rounds(o) AS (VALUES " + ", ".join(f"({t})" for t in range(len(lengths))) + ")"
    total = "(SELECT count(*) FROM ex)"
    mom = "avg(x1 * x1) AS a11, avg(x1 * x2) AS a12, avg(x2 * x2) AS a22, avg(x1 * y) AS c1, avg(x2 * y) AS c2"
    inner = f"id AS (SELECT o, k, {P.position(sql_uniform(repr(str(SEED)), repr('inner'), 'o', 'k', 'draw'), total)} AS gpos FROM seq, range(2) q(draw)), im AS MATERIALIZED (SELECT o, k, {mom} FROM id JOIN placed USING (gpos) GROUP BY 1, 2)"
    if anchor == "stratified":
        pick = f"ad AS (SELECT o, stratum, w, {P.position(sql_uniform(repr(str(SEED)), repr('anchor'), 'o', 'stratum', '0'), 'n')} AS pos FROM rounds, strata), ap AS (SELECT o, ad.w, placed.* FROM ad JOIN placed USING (stratum, pos))"
        am = "am AS MATERIALIZED (SELECT o, sum(w * x1 * x1) AS a11, sum(w * x1 * x2) AS a12, sum(w * x2 * x2) AS a22, sum(w * x1 * y) AS c1, sum(w * x2 * y) AS c2 FROM ap GROUP BY 1)"
        anchors = f"{pick}, {am}"
    elif anchor == "batch":
        anchors = f"ad AS (SELECT o, {P.position(sql_uniform(repr(str(SEED)), repr('anchor'), 'o', '0', 'draw'), total)} AS gpos FROM rounds, range({_BATCH}) q(draw)), am AS MATERIALIZED (SELECT o, {mom} FROM ad JOIN placed USING (gpos) GROUP BY 1)"
    else:
        anchors = f"am AS MATERIALIZED (SELECT o, m.* FROM rounds, (SELECT {mom} FROM ex) m)"
    grad = lambda m, a, b: (f"(2.0 * ({m}.a11 * {a} + {m}.a12 * {b} - {m}.c1))", f"(2.0 * ({m}.a12 * {a} + {m}.a22 * {b} - {m}.c2))")
    if kind == "minibatch":
        g1, g2 = "0.0", "0.0"
        v1, v2 = grad("im", "th1", "th2")
    elif kind == "stratified":
        g1, g2 = "0.0", "0.0"
        v1, v2 = grad("am", "th1", "th2")
    else:
        h1, h2 = grad("am", "th1", "th2")
        g1, g2 = f"CASE WHEN seq.k = 0 THEN {h1} ELSE r.g1 END", f"CASE WHEN seq.k = 0 THEN {h2} ELSE r.g2 END"
        d1, d2 = "(th1 - r.p1)", "(th2 - r.p2)"
        v1 = f"CASE WHEN seq.k = 0 THEN {h1} ELSE 2.0 * (im.a11 * {d1} + im.a12 * {d2}) + r.g1 END"
        v2 = f"CASE WHEN seq.k = 0 THEN {h2} ELSE 2.0 * (im.a12 * {d1} + im.a22 * {d2}) + r.g2 END"
    stop = f"(k0 > 0 AND (stopped = o0 OR v1 * v1 + v2 * v2 <= {gamma!r} * (ng1 * ng1 + ng2 * ng2)))" if gamma is not None else "false"
    moves = {
        "sgd": ("0.0", "0.0", "0.0", "0.0", "v{0}"), "momentum": ("0.9 * m1 + v1", "0.9 * m2 + v2", "0.0", "0.0", "nm{0}"),
        "rmsprop": ("0.0", "0.0", "0.9 * q1 + (1 - 0.9) * v1 * v1", "0.9 * q2 + (1 - 0.9) * v2 * v2", "v{0} / (sqrt(nq{0}) + 1e-8)"),
        "adagrad": ("0.0", "0.0", "q1 + v1 * v1", "q2 + v2 * v2", "v{0} / (sqrt(nq{0}) + 1e-8)"),
        "adam": ("0.9 * m1 + (1 - 0.9) * v1", "0.9 * m2 + (1 - 0.9) * v2", "0.999 * q1 + (1 - 0.999) * v1 * v1", "0.999 * q2 + (1 - 0.999) * v2 * v2", "(nm{0} / (1 - pow(0.9, c + 1))) / (sqrt(nq{0} / (1 - pow(0.999, c + 1))) + 1e-8)"),
    }[rule]
    m1, m2, q1, q2, move = moves
    hash_bits = "(('0x' || substr(md5(concat_ws('|', '7', 'stratum', series_id, t0)), 1, 13))::BIGINT)"
    laid = f"{_S6X}, {P.assigned(f'{hash_bits} % 16' if kind == 'hashed' else 'series_id')}, {P.LAYOUT}".replace("placed AS (", "placed AS MATERIALIZED (")
    return f"""WITH RECURSIVE {laid}, {seq}, {rounds}, {inner}, {anchors},
r AS (SELECT 0 AS s, -1 AS o, -1 AS k, true AS active, -1 AS stopped, 0 AS c, 0.0::DOUBLE AS th1, 0.0::DOUBLE AS th2, 0.0::DOUBLE AS p1, 0.0::DOUBLE AS p2, 0.0::DOUBLE AS g1, 0.0::DOUBLE AS g2, 0.0::DOUBLE AS m1, 0.0::DOUBLE AS m2, 0.0::DOUBLE AS q1, 0.0::DOUBLE AS q2
UNION ALL SELECT s0, o0, k0, NOT halt, CASE WHEN halt THEN o0 ELSE stopped END, c + 1, CASE WHEN halt THEN th1 ELSE th1 - {lr!r} * ({move.format(1)}) END, CASE WHEN halt THEN th2 ELSE th2 - {lr!r} * ({move.format(2)}) END, np1, np2, ng1, ng2, nm1, nm2, nq1, nq2
FROM (SELECT *, {stop} AS halt, ({m1})::DOUBLE AS nm1, ({m2})::DOUBLE AS nm2, ({q1})::DOUBLE AS nq1, ({q2})::DOUBLE AS nq2 FROM (
 SELECT r.c, r.stopped, r.th1, r.th2, r.m1, r.m2, r.q1, r.q2, seq.s AS s0, seq.o AS o0, seq.k AS k0, CASE WHEN seq.k = 0 THEN th1 ELSE r.p1 END AS np1, CASE WHEN seq.k = 0 THEN th2 ELSE r.p2 END AS np2, ({g1})::DOUBLE AS ng1, ({g2})::DOUBLE AS ng2, ({v1})::DOUBLE AS v1, ({v2})::DOUBLE AS v2
 FROM r JOIN seq ON seq.s = r.s + 1 JOIN im ON im.o = seq.o AND im.k = seq.k JOIN am ON am.o = {'0' if kind == 'minibatch' else 'seq.o'}) a) b)
SELECT '{name}' AS method, o::INTEGER AS "outer", k::INTEGER AS "inner", round(th1, 6) AS theta1, round(th2, 6) AS theta2 FROM r WHERE s > 0 AND active"""


for _name in FITS:
    register(_name, _fit_query(_name), _fit_sql(_name))


def least_squares_ar(spark, d):
    theta, loss = gradients.least_squares(nation_examples(spark, d), 2)
    return spark.createDataFrame([(float(theta[0]), float(theta[1]), loss)], "theta1 double, theta2 double, loss double").select(*_r("theta1", "theta2", "loss"))


register("least_squares_ar", least_squares_ar,
         f"""WITH {_S6X}, m AS (SELECT avg(x1 * x1) AS a11, avg(x1 * x2) AS a12, avg(x2 * x2) AS a22, avg(x1 * y) AS c1, avg(x2 * y) AS c2, avg(y * y) AS yy FROM ex),
t AS (SELECT (a22 * c1 - a12 * c2) / (a11 * a22 - a12 * a12) AS t1, (a11 * c2 - a12 * c1) / (a11 * a22 - a12 * a12) AS t2, c1, c2, yy FROM m) SELECT round(t1, 6) AS theta1, round(t2, 6) AS theta2, round(yy - c1 * t1 - c2 * t2, 6) AS loss FROM t""")  # fmt: skip


def counterexample_variance(spark, d):
    """Gradient variance of the two-series instances by the kernel of AR(p), at parameters that sum to 1/2, beside 4 delta**4 p. Every order gives an instance, whose delta
    is its price in units of 500,000, cut to two digits."""
    price = (F.floor(tables.cents(F.col("o_totalprice")) / 500_000.0) / 100.0).alias("delta")
    grid = tables.table(spark, d, "orders").select(price, F.explode(F.array(F.lit(1.0), F.lit(-1.0))).alias("sign"))
    out = None
    for p in (1, 4, 16, 64):
        ex = grid.select("delta", "sign", (F.col("sign") * F.col("delta")).alias("y"), *[F.col("delta").alias(f"x{j}") for j in range(1, p + 1)])
        inside = F.round(sum((F.var_pop(f"g{j}") for j in range(1, p + 1)), F.lit(0.0)), 6).alias("variance")
        g = gradients.with_gradient(ex, [0.5 / p] * p).groupBy("delta").agg(F.count_if(F.col("sign") > 0).alias("orders"), inside)
        one = g.select(F.lit(p).alias("p"), "delta", "orders", "variance", F.round(F.lit(4.0 * p) * F.pow("delta", F.lit(4)), 6).alias("bound"))
        out = one if out is None else out.unionByName(one)
    return out


register("counterexample_variance", counterexample_variance,
         f"""SELECT p, delta, orders, round(p * 4.0 * pow(delta, 4), 6) AS variance, round(4.0 * pow(delta, 4) * p, 6) AS bound FROM (VALUES (1), (4), (16), (64)) a(p),
(SELECT floor({P.cents('o_totalprice')} / 500000.0) / 100.0 AS delta, count(*) AS orders FROM orders GROUP BY 1) b""")  # fmt: skip


def complexity_rows(spark, d):
    """Orders of example gradients to reach 0.1, with measured variances at 0 of the nation strata."""
    ex = nation_examples(spark, d)
    inside = measures.stratum_variance(strata.PerSeries().assign(ex), ZERO).orderBy("stratum").collect()
    total = measures.gradient_variance(ex, ZERO).first()
    a, c, yy = gradients.matrices(gradients.moments(ex, [], 2).first().asDict(), 2)
    gap, smooth = float(c @ np.linalg.solve(a, c)), float(2 * np.linalg.eigvalsh(a).max())
    table = complexity_table(gap, smooth, 0.1, total["variance"], [r["w"] for r in inside], [r["variance"] for r in inside], total["n"])
    return spark.createDataFrame([(k, math.log10(v)) for k, v in table.items()], "method string, log10_gradients double").select("method", *_r("log10_gradients"))


register("complexity_rows", complexity_rows,
         f"""WITH {_BY_NATION}, {P.gradients(ZERO)}, dep AS ({P.dependency()}), m AS (SELECT avg(x1 * x1) AS a11, avg(x1 * x2) AS a12, avg(x2 * x2) AS a22, avg(x1 * y) AS c1, avg(x2 * y) AS c2, count(*) AS n FROM ex),
k AS (SELECT (c1 * (a22 * c1 - a12 * c2) + c2 * (a11 * c2 - a12 * c1)) / (a11 * a22 - a12 * a12) * (a11 + a22 + sqrt((a11 - a22) * (a11 - a22) + 4 * a12 * a12)) AS dl, n, dep.* FROM m, dep)
SELECT 'anchored_stratified' AS method, round(log10(dl * pow(strata * stratified, 2.0 / 3) * pow(0.1, -10.0 / 3)), 6) AS log10_gradients FROM k UNION ALL SELECT 'anchored_equal_strata', round(log10(dl * pow(mean_inside, 2.0 / 3) * pow(0.1, -10.0 / 3)), 6) FROM k
UNION ALL SELECT 'batch_anchor', round(log10(dl * pow(total, 2.0 / 3) * pow(0.1, -10.0 / 3)), 6) FROM k UNION ALL SELECT 'full_anchor', round(log10(dl * pow(n, 2.0 / 3) * pow(0.1, -2)), 6) FROM k UNION ALL SELECT 'lower_bound', round(log10(dl * total * pow(0.1, -4)), 6) FROM k""")  # fmt: skip

# Neural forecasters: no SQL; tests check gradients by differences and that losses fall.


def fit_segments(spark, points, model, policy, tau_c, tau_p, rule="adam", lr=0.003, outer=8, inner=6, minibatch=8, freq="hour", method="anchored_adam"):
    """method, outer, grad_evals, train_loss before and after a short anchored run of any forecaster."""
    segs = series.segments(points, tau_c, tau_p).join(points.select("series_id", F.col("t").alias("t0"), "bucket"), ["series_id", "t0"])
    placed, table = strata.layout(policy.assign(segs))
    placed = prepared(placed.select("stratum", "pos", "gpos", "context", "target"))
    problem = SegmentProblem(model, placed, prepared(table), [inner] * outer, minibatch, 1, SEED)
    start = model.start(3)
    fit = loop.anchored_fit(problem, make_rule(rule, lr), [inner] * outer, start, method=method)
    before, after = evaluate(placed, model, start), evaluate(placed, model, fit.theta)
    return spark.createDataFrame([(method, len(fit.trace.rows), fit.trace.grad_evals, before, after)], "method string, updates int, grad_evals long, loss_before double, loss_after double")


register("fit_mlp_nll", lambda s, d: fit_segments(s, series.hourly_share(s, d), MLPModel(24, 6, 16, 2), _WEEK, 24, 6, method="mlp_nll"))
register("fit_lstm_mse", lambda s, d: fit_segments(s, series.hourly_share(s, d), LSTMModel(12, 3, 8, 2, mse_loss), _WEEK, 12, 3, lr=0.01, method="lstm_mse"))
register("fit_residual_stack_mape", lambda s, d: fit_segments(s, series.scaled_by_mean(series.monthly_by_nation(s, d)), ResidualStackModel(8, 2, 3, 16, 2), strata.PerSeries(), 8, 2, method="residual_stack_mape"))
