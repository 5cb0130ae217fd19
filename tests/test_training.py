import math
from fractions import Fraction

import numpy as np
import pytest

from stratafit.functions import losses
from stratafit.models import arrow_kernel
from stratafit.models.forecasters import ARModel, LSTMModel, MLPModel, ResidualStackModel, VARModel, gaussian_nll_loss, mape_loss, mse_loss, pinball_loss, student_nll_loss
from stratafit.operators import gradients, measures, sampling, series, strata
from stratafit.optim import loop
from stratafit.optim.problems import ArrayProblem, MomentsProblem, tune
from stratafit.optim.rules import RULES, make_rule
from stratafit.plans import training_queries as Q
from stratafit.sources import synthetic
from stratafit.theory import checks


@pytest.fixture(scope="module")
def toy(spark):
    ex = series.lag_examples(synthetic.toy(spark, 4000), 2).orderBy("t0").toPandas()
    return ex[["x1", "x2"]].to_numpy(), ex["y"].to_numpy(), ex["t0"].to_numpy() % 8


def ar_problem(toy, **kw):
    x, y, s = toy
    gradient = lambda i, theta: (2 * (x[i] @ theta - y[i])[:, None] * x[i]).mean(axis=0)
    return ArrayProblem(gradient, len(y), 2, kw.pop("strata", s), **kw)


def test_rules_by_hand():
    g = [np.array([1.0, -2.0]), np.array([0.5, 1.0]), np.array([-1.0, 0.0])]
    run = lambda rule: [t := np.zeros(2)] and [t := rule.step(t, v) for v in g][-1]
    assert np.allclose(run(make_rule("sgd", 0.1)), [-0.05, 0.1])
    assert np.allclose(run(make_rule("momentum", 0.1)), [-0.1 * (1 + 1.4 + 0.26), 0.1 * (2 + 0.8 + 0.72)])
    assert np.allclose(run(make_rule("adagrad", 0.1)), [-0.1 * (1 + 0.5 / math.sqrt(1.25) - 1 / 1.5), 0.1 * (1 - 1 / math.sqrt(5))])
    one = make_rule("adam", 0.1).step(np.zeros(2), g[0])
    assert np.allclose(one, [-0.1, 0.1])
    assert np.allclose(make_rule("rmsprop", 0.1).step(np.zeros(2), g[0]), [-0.1 / math.sqrt(0.1), 0.1 / math.sqrt(0.1)])


@pytest.mark.parametrize("rule", RULES)
def test_rules_respect_zeros(rule):
    assert checks.is_zero_respecting(make_rule(rule, 0.1))


def test_losses_by_hand():
    y, f = np.array([1.0, 0.0, -2.0]), np.array([2.0, 1.0, -1.0])
    assert losses.np_mse(y, f) == 1 and losses.np_mape(y, f) == 0.75 and abs(losses.np_pinball(y, f, 0.9) - 0.1) < 1e-12
    assert abs(losses.np_gaussian_nll(np.zeros(1), np.zeros(1), np.ones(1)) - 0.5 * math.log(2 * math.pi)) < 1e-12
    assert abs(losses.np_student_nll(np.ones(1), np.zeros(1), np.ones(1), 1e7) - losses.np_gaussian_nll(np.ones(1), np.zeros(1), np.ones(1))) < 1e-5
    assert math.isnan(losses.np_mape(np.zeros(2), np.ones(2)))


def test_loss_columns_agree_with_numpy(spark):
    from pyspark.sql import functions as F

    rows = [(1.0, 2.0, 0.5), (0.0, 1.0, 2.0), (-3.0, -2.5, 1.0)]
    df = spark.createDataFrame(rows, "y double, f double, s double")
    y, f, s = (np.array(c) for c in zip(*rows, strict=True))
    cy, cf, cs = F.col("y"), F.col("f"), F.col("s")
    got = df.agg(F.avg(losses.mse(cy, cf)), F.avg(losses.gaussian_nll(cy, cf, cs)), F.avg(losses.student_nll(cy, cf, cs, 5.0)), F.avg(losses.mape(cy, cf)), F.avg(losses.pinball(cy, cf, 0.3)), F.avg(losses.mape(cy, cf, "eps", 1.0)), F.avg(losses.kl_gaussian(cf, cs, cf, cs))).first()
    want = [losses.np_mse(y, f), losses.np_gaussian_nll(y, f, s), losses.np_student_nll(y, f, s, 5.0), losses.np_mape(y, f), losses.np_pinball(y, f, 0.3), np.mean(np.abs(f - y) / np.maximum(np.abs(y), 1)), 0]
    assert np.allclose(list(got), want)
    kl = df.select(losses.kl_discrete(F.array(F.lit(0.5), F.lit(0.5), F.lit(0.0)), F.array(F.lit(0.25), F.lit(0.5), F.lit(0.25)))).first()[0]
    assert abs(kl - 0.5 * math.log(2)) < 1e-12


MODELS = [ARModel(4), VARModel(2, 3), MLPModel(6, 2, 5, 2), MLPModel(6, 2, 5, 2, loss=student_nll_loss(4.0)), MLPModel(6, 2, 5, 1, 1, pinball_loss(0.8)), LSTMModel(5, 2, 3, 2), ResidualStackModel(6, 2, 3, 4, 2)]


@pytest.mark.parametrize("model", MODELS, ids=lambda m: f"{type(m).__name__}{m.size}")
def test_gradients_by_central_differences(model):
    rng = np.random.default_rng(0)
    width = 6 if not isinstance(model, (ARModel, VARModel, LSTMModel)) else {ARModel: 4, VARModel: 6, LSTMModel: 5}[type(model)]
    x, y = rng.normal(size=(7, width)), rng.normal(size=(7, 1 if isinstance(model, ARModel) else 3 if isinstance(model, VARModel) else 2)) + 0.3
    theta = model.start(1) + rng.normal(size=model.size) * 0.1
    loss, g = model.loss_grad(theta, x, y)
    assert abs(loss - model.loss_only(theta, x, y)) < 1e-12
    for i in rng.choice(model.size, min(25, model.size), replace=False):
        e = np.zeros(model.size)
        e[i] = 1e-6
        d = (model.loss_only(theta + e, x, y) - model.loss_only(theta - e, x, y)) / 2e-6
        assert abs(d - g[i]) < 1e-5 * max(1, abs(d))


def test_published_sizes():
    assert LSTMModel(72, 24).size == 4 * 100 * (1 + 100 + 1) + 4 * 100 * 201 + 100 * 24 + 24
    assert MLPModel(72, 24).size == 72 * 80 + 3 * 6400 + 4 * 80 + 2 * (80 * 24 + 24)
    assert ResidualStackModel(72, 24, 30).stacks == 30 and mape_loss and gaussian_nll_loss and mse_loss


def test_three_gradient_engines_agree(spark, sf):
    ex = Q.nation_examples(spark, sf)
    theta = np.array([0.3, 0.2])
    sql = gradients.full_gradient(ex, theta).first()
    a, c, yy = gradients.matrices(gradients.moments(ex, [], 2).first().asDict(), 2)
    pdf = ex.toPandas()
    x, y = pdf[["x1", "x2"]].to_numpy(), pdf["y"].to_numpy()
    plain = (2 * (x @ theta - y)[:, None] * x).mean(axis=0)
    assert np.allclose([sql["g1"], sql["g2"]], plain, atol=1e-9) and np.allclose(2 * (a @ theta - c), plain, atol=1e-9)
    from pyspark.sql import functions as F

    segs = strata.PerSeries().assign(ex).select("stratum", F.array("x2", "x1").alias("context"), F.array("y").alias("target"))
    arrow = arrow_kernel.gradient_by_stratum(segs, ARModel(2), theta, squares=True)
    n = sum(v[0] for v in arrow.values())
    assert n == len(y) and np.allclose(sum(v[0] * v[2] for v in arrow.values()) / n, plain, atol=1e-9)
    assert abs(sum(v[0] * v[3] for v in arrow.values()) / n - (np.linalg.norm(2 * (x @ theta - y)[:, None] * x, axis=1) ** 2).mean()) < 1e-8
    assert abs(arrow_kernel.evaluate(segs, ARModel(2), theta) - ((x @ theta - y) ** 2).mean()) < 1e-9
    best, least = gradients.least_squares(ex, 2)
    assert np.allclose(best, np.linalg.lstsq(x, y, rcond=None)[0]) and abs(least - ((x @ best - y) ** 2).mean()) < 1e-9


def test_variance_splits_and_controls(spark):
    ex = series.lag_examples(synthetic.toy(spark, 4000), 2)
    right = measures.variance_dependency(strata.ModPeriod(8).assign(ex), (0.0, 0.0)).first()
    wrong = measures.variance_dependency(strata.ModPeriod(8).assign(series.lag_examples(synthetic.toy(spark, 4000, 1.0), 2)), (0.0, 0.0)).first()
    chance = measures.variance_dependency(measures.relabelled(strata.ModPeriod(8).assign(ex)), (0.0, 0.0)).first()
    assert right["within_share"] < 0.15 and wrong["within_share"] > 0.98 and chance["within_share"] > 0.98
    assert abs(right["within"] + right["between"] - right["total"]) < 1e-9
    equal = measures.variance_dependency(strata.EqualSize(8).assign(ex), (0.3, 0.1)).first()
    assert equal["dependency"] <= equal["total"] * 1.01
    spread = {r["sampler"]: r["empirical"] for r in measures.sampler_variance(strata.ModPeriod(8).assign(ex), (0.0, 0.0), 200, 1, 1).collect()}
    assert spread["stratified"] < 0.3 * spread["uniform"]
    assert abs(spread["stratified"] / right["stratified"] - 1) < 0.3


def test_unequal_strata_can_be_worse():
    w = np.array([901 / 1000] + [1 / 1000] * 99)
    v = np.array([2.0] + [0.0] * 99)
    assert len(w) * (w * w * v).sum() > 2.0 * 50


def test_estimator_moments_exactly():
    values = [[Fraction(1), Fraction(4)], [Fraction(-2), Fraction(0), Fraction(5)]]
    for b in (1, 2):
        mean, var = checks.stratified_moments(values, b)
        assert mean == Fraction(8, 5) and var == checks.stratified_variance_formula(values, b)


@pytest.mark.parametrize("p,delta", [(1, 1.0), (4, 2.0), (16, 1.0), (64, 2.0)])
def test_lower_bound_instance(p, delta):
    x, y = checks.heterogeneous_ar(p, delta)
    for theta in (np.zeros(p), np.random.default_rng(p).normal(size=p)):
        assert abs(checks.variance(checks.ar_gradients(x, y, theta)) - 4 * delta**4 * p) < 1e-6 * delta**4 * p
        assert checks.variance(checks.ar_gradients(x[:1], y[:1], theta)) == 0


def test_sparse_instance_needs_every_kind():
    x, y = checks.sparse_ar(8, 1.0)
    theta, rule = np.zeros(8), make_rule("sgd", 0.1)
    for j in (0, 3, 3):
        theta = rule.step(theta, checks.ar_gradients(x[[j]], y[[j]], theta)[0])
    assert set(np.flatnonzero(theta)) == {0, 3}
    assert np.all(rule.step(np.zeros(8), checks.ar_gradients(x, y, np.zeros(8)).mean(axis=0)) != 0)


def test_complexity_and_precondition():
    w, v = [0.25] * 4, [1.0, 2.0, 3.0, 2.0]
    t = checks.complexity_table(2.0, 3.0, 0.1, 10.0, w, v, 1000)
    assert abs(t["anchored_stratified"] / t["anchored_equal_strata"] - 1) < 1e-9
    same = checks.complexity_table(2.0, 3.0, 0.1, 2.0, w, [2.0] * 4, 1000)
    assert abs(same["anchored_stratified"] / same["batch_anchor"] - 1) < 1e-9
    ratio = [checks.complexity_table(1, 1, e, 2.0, w, v, 10)["lower_bound"] / checks.complexity_table(1, 1, e, 2.0, w, v, 10)["batch_anchor"] for e in (0.1, 0.01)]
    assert abs(ratio[1] / ratio[0] - 10 ** (2 / 3)) < 1e-6
    assert checks.complexity_table(1, 1, 0.1, 2.0, [0.1] * 10, [0.0] * 10, 10)["anchored_stratified"] > 0
    assert checks.precondition(w, v, 1.0) == (True, 0.5) and checks.precondition(w, v, 0.1)[0] is False


def test_smoothness_by_differences(toy):
    x, y, _ = toy
    each, whole = checks.smoothness(x)
    rng = np.random.default_rng(0)
    for _ in range(20):
        a, b = rng.normal(size=2), rng.normal(size=2)
        diff = checks.ar_gradients(x, y, a) - checks.ar_gradients(x, y, b)
        assert np.linalg.norm(diff, axis=1).max() <= each * np.linalg.norm(a - b) * (1 + 1e-9)
        assert np.linalg.norm(diff.mean(axis=0)) <= whole * np.linalg.norm(a - b) * (1 + 1e-9)


def test_first_inner_step_is_the_anchor(toy):
    fits = [loop.anchored_fit(ar_problem(toy, seed=3), make_rule("sgd", 0.01), [3, 0, 4], reuse_first=r) for r in (True, False)]
    assert np.allclose(fits[0].theta, fits[1].theta)
    assert fits[1].trace.grad_evals - fits[0].trace.grad_evals == 2 * 2 and fits[0].trace.anchor_evals == 24
    assert fits[0].trace.grad_evals == 3 * 8 + 2 * (2 + 3)
    assert abs(fits[0].trace.overhead() - 24 / 34) < 1e-12


def test_finest_strata_are_the_full_anchor(toy):
    x, y, _ = toy
    small = (x[:60], y[:60], np.arange(60))
    kw = {"seed": 1}
    problem = ar_problem(small, anchor="full", **kw)
    g, n = problem.anchor(0, np.ones(2))
    by_strata = sum(1 / 60 * problem.gradient(np.array([i]), np.ones(2)) for i in range(60))
    assert n == 60 and np.allclose(g, by_strata, atol=1e-12)
    finest, _ = ar_problem(small, per_stratum=1, **kw).anchor(0, np.ones(2))
    assert np.allclose(finest, g, atol=1e-12)


def test_hashed_strata_match_a_batch_anchor(toy):
    x, y, _ = toy
    labels = np.random.default_rng(0).permutation(len(y)) % 8
    theta = np.zeros(2)
    draw = lambda kind: np.array([ar_problem(toy, strata=labels, seed=s, anchor=kind, batch=8).anchor(0, theta)[0] for s in range(600)])
    a, b = draw("stratified"), draw("batch")
    full = ar_problem(toy).gradient(np.arange(len(y)), theta)
    assert np.abs(a.mean(axis=0) - full).max() < 0.2 and abs(a.var(axis=0).sum() / b.var(axis=0).sum() - 1) < 0.25


def test_one_stratum_is_a_plain_minibatch(toy):
    x, y, _ = toy
    one = ar_problem(toy, strata=np.zeros(len(y), int), per_stratum=5, seed=2)
    g, n = one.anchor(4, np.ones(2))
    assert n == 5 and np.allclose(g, one.gradient(np.random.default_rng((2, 2, 4)).integers(0, len(y), 5), np.ones(2)))


def test_scaling_the_series_scales_variance(toy):
    x, y, _ = toy
    v = [checks.variance(checks.ar_gradients(c * x, c * y, np.array([0.2, 0.1]))) for c in (1.0, 3.0)]
    assert abs(v[1] / v[0] - 81) < 1e-6


@pytest.mark.parametrize("lr", [0.001, 0.003, 0.01])
def test_anchored_is_stationary_where_the_baselines_are_noisy(toy, lr):
    """Mean squared gradient norm over the last fifth of the updates, at equal example gradients, over 20 seeds."""
    x, y, _ = toy
    a, c = x.T @ x / len(y), x.T @ y / len(y)
    labels = np.random.default_rng(1).permutation(len(y)) % 8

    def tail(method, seed):
        rows = []
        evaluate = lambda th: rows.append(float((2 * (a @ th - c)) @ (2 * (a @ th - c)))) or {}
        rule, budget = make_rule("sgd", lr), loop.Budget(grad_evals=12_000)
        if method == "sgd":
            loop.minibatch_fit(ar_problem(toy, seed=seed), rule, [(0, k) for k in range(12_000)], budget=budget, evaluate=evaluate)
        else:
            p = ar_problem(toy, seed=seed, strata=labels if method == "hashed" else toy[2])
            loop.anchored_fit(p, rule, sampling.inner_lengths(2000, 8, seed), budget=budget, evaluate=evaluate)
        return np.mean(rows[-len(rows) // 5 :])

    seeds = range(6) if lr == 0.003 else range(3)
    got = {m: np.mean([tail(m, s) for s in seeds]) for m in ("sgd", "hashed", "anchored")}
    assert got["anchored"] < got["hashed"] and (lr < 0.003 or got["anchored"] < got["sgd"])


def test_return_policies_gamma_and_budgets(toy):
    x, y, _ = toy
    evaluate = lambda th: {"train_loss": float(((x @ th - y) ** 2).mean())}
    best = loop.anchored_fit(ar_problem(toy), make_rule("sgd", 0.02), [4] * 10, return_policy="best", evaluate=evaluate)
    last = loop.anchored_fit(ar_problem(toy), make_rule("sgd", 0.02), [4] * 10, evaluate=evaluate)
    assert evaluate(best.theta)["train_loss"] <= evaluate(last.theta)["train_loss"]
    sampled = loop.anchored_fit(ar_problem(toy), make_rule("sgd", 0.02), [4] * 10, return_policy="sampled", seed=4)
    assert not np.allclose(sampled.theta, last.theta)
    stopped = loop.anchored_fit(ar_problem(toy), make_rule("sgd", 0.02), [40] * 3, gamma=0.5)
    assert len(stopped.trace.rows) < 120
    assert loop.anchored_fit(ar_problem(toy), make_rule("sgd", 0.02), [40] * 3, budget=loop.Budget(updates=7)).trace.updates == 7
    with pytest.raises(ValueError):
        loop.anchored_fit(ar_problem(toy), make_rule("sgd", 0.02), [1], return_policy="first")
    tuned = tune(lambda lr: evaluate(loop.minibatch_fit(ar_problem(toy), make_rule("sgd", lr), [(0, k) for k in range(200)]).theta)["train_loss"], [1e-4, 1e-2, 1e3])
    assert tuned[0][0] == 1e-2 and len(tuned) == 3


def test_traces_compare(spark, toy):
    x, y, _ = toy
    a, c = x.T @ x / len(y), x.T @ y / len(y)
    evaluate = lambda th: {"train_loss": float(((x @ th - y) ** 2).mean()), "grad_norm": float(np.linalg.norm(2 * (a @ th - c)))}
    traces = None
    for run in range(5):
        for method, p in (("sgd", None), ("anchored_stratified", 1)):
            f = loop.minibatch_fit(ar_problem(toy, seed=run), make_rule("sgd", 0.01), [(0, k) for k in range(60)], evaluate=evaluate, run=str(run)) if p is None else loop.anchored_fit(ar_problem(toy, seed=run), make_rule("sgd", 0.01), [8] * 8, evaluate=evaluate, run=str(run))
            t = f.trace.to_df(spark)
            traces = t if traces is None else traces.unionByName(t)
    rows = {r["method"]: r for r in measures.comparison(traces).collect()}
    assert set(rows) == {"sgd", "anchored_stratified"} and all(r["runs"] == 5 and r["deviation"] >= 0 for r in rows.values())
    hits = measures.first_hit(traces, 1e9).collect()
    assert len(hits) == 10 and measures.first_hit(traces, -1.0).count() == 0


def test_moments_replay_equals_arrays(spark, sf):
    ex = Q.nation_examples(spark, sf)
    placed, table = strata.layout(strata.PerSeries().assign(ex))
    schedule = sampling.build_schedule(spark, [3, 2], table, ex.count(), 2, 3, 1)
    problem = MomentsProblem.collect(placed, table, schedule, 2)
    rows = {(r["stratum"], r["pos"]): r for r in placed.collect()}
    by_g = {r["gpos"]: r for r in rows.values()}
    w = {r["stratum"]: r["w"] for r in table.collect()}
    theta = np.array([0.4, -0.1])
    grad = lambda r: 2 * (theta @ [r["x1"], r["x2"]] - r["y"]) * np.array([r["x1"], r["x2"]])
    draws = schedule.collect()
    inner = np.mean([grad(by_g[d["gpos"]]) for d in draws if d["role"] == "inner" and (d["outer"], d["inner"]) == (0, 1)], axis=0)
    anchor = sum(w[d["stratum"]] * grad(rows[d["stratum"], d["pos"]]) / 2 for d in draws if d["role"] == "anchor" and d["outer"] == 1)
    assert np.allclose(problem.inner(0, 1, theta)[0], inner) and np.allclose(problem.anchor(1, theta)[0], anchor)


@pytest.mark.parametrize("name", ["fit_mlp_nll", "fit_lstm_mse", "fit_residual_stack_mape"])
def test_neural_fits_lower_the_loss(spark, sf, name):
    from stratafit.plans import catalogue

    r = catalogue.queries()[name](spark, sf).first()
    assert r["loss_after"] < r["loss_before"] and r["grad_evals"] > 0


def test_equal_budget_is_registered_whole(monkeypatch):
    import inspect

    from stratafit.plans import catalogue, workload_queries

    whole = inspect.signature(workload_queries.equal_budget_table)
    monkeypatch.setattr(workload_queries, "equal_budget_table", lambda *a, **k: whole.bind(*a, **k))
    call = catalogue.queries()["workload_equal_budget"](None, "")
    call.apply_defaults()
    # An outer step of 49 strata takes 49 example gradients for the anchor and two batches of 8 in each of 49 inner steps on average.
    assert call.arguments["runs"] == 5 and call.arguments["tuned"] and call.arguments["grad_evals"] >= 5 * (49 + 16 * 49)


@pytest.mark.parametrize("kind", ["stratified", "batch", "full"])
def test_spark_anchors_and_streamed_minibatches_equal_arrays(spark, sf, kind):
    """Jobs over placed examples against arrays in memory, a whole anchored run of a network."""
    from pyspark.sql import functions as F

    from stratafit.operators import series
    from stratafit.optim.problems import SegmentProblem

    segs = series.segments(series.scaled_by_mean(series.monthly_by_nation(spark, sf)), 6, 2)
    placed, table = strata.layout(strata.PerSeries().assign(segs))
    placed = placed.select("stratum", "pos", "gpos", "context", "target").checkpoint()
    pdf = placed.orderBy("gpos").toPandas()
    x, y, model = np.array(pdf["context"].tolist()), np.array(pdf["target"].tolist()), MLPModel(6, 2, 5, 2)
    arrays = ArrayProblem(lambda i, th: model.loss_grad(th, x[i], y[i])[1], len(x), model.size, pdf["stratum"].to_numpy(), 4, 2, 5, kind, shared_draws=True)
    jobs = SegmentProblem(model, placed, table, [3, 2], 4, 2, 5, kind)
    runs = [loop.anchored_fit(p, make_rule("sgd", 0.01), [3, 2], model.start(1)) for p in (arrays, jobs)]
    assert np.abs(runs[0].theta - runs[1].theta).max() < 1e-9 and runs[0].trace.grad_evals == runs[1].trace.grad_evals
    assert placed.agg(F.max("gpos")).first()[0] == len(x) - 1


def test_composed_policies_without_keys(spark, sf):
    from pyspark.sql import functions as F

    from stratafit.operators import series

    ex = Q.nation_examples(spark, sf).withColumn("features", F.array("x1", "x2"))
    found = strata.Compose([strata.KMeansPolicy(3, level="series"), strata.CalendarHash(["month"], "month")]).assign(ex)
    month = strata.CalendarHash(["month"], "month").key()
    parts = found.groupBy("stratum").agg(F.countDistinct(month).alias("months"), F.min(month).alias("m")).collect()
    assert found.count() == ex.count() and all(r["months"] == 1 for r in parts) and sorted(r["stratum"] for r in parts) == list(range(len(parts)))
    assert found.groupBy("series_id", month.alias("m")).agg(F.countDistinct("stratum").alias("n")).filter("n > 1").count() == 0
    both = strata.Compose([strata.WeekdaySeason(3), strata.PerSeries()]).assign(series.lag_examples(series.daily_by_region(spark, sf), 2))
    assert both.groupBy("series_id").agg(F.countDistinct("stratum").alias("n")).filter("n != 21").count() == 0


def test_workloads_behave_alike_on_arrays_and_by_jobs(spark, sf):
    from stratafit.plans import workload_queries as V

    data = V.families(spark, 3, 120)
    for method in ("sgd", "batch_anchor", "anchored_stratified"):
        task = V.Task("mlp_nll", method, 0.01, 2, updates=6, minibatch=2)
        here, there = V.array_fit(data.arrays, task), V.spark_fit(data, task)
        assert np.abs(here[0].theta - there[0].theta).max() < 1e-9 and abs(here[1] - there[1]) < 1e-9 and abs(here[2] - there[2]) < 1e-9
    assert V.split_dataset is not None and V.families(spark, 3, 120).train.count() == len(data.arrays["x"])


def test_curves_keep_the_best_step_sizes_with_test_loss_and_time(spark, sf):
    from stratafit.plans import workload_queries as V

    curves = V.training_curves(spark, V.family_vectors(spark, sf), "var_mse", ("sgd", "anchored_stratified"), {"sgd": 2}, 200, 4).toPandas()
    assert curves.groupby("method")["lr"].nunique().to_dict() == {"sgd": 2, "anchored_stratified": 1}
    for _, c in curves.sort_values("update").groupby(["method", "lr"]):
        assert c["train_loss"].iloc[-1] < c["train_loss"].iloc[0] and c["test_loss"].notna().all() and c["seconds"].is_monotonic_increasing and c["grad_evals"].iloc[-1] >= 200


def test_strata_lower_the_variance_of_networks_gradients(spark, sf):
    from stratafit.plans import workload_queries as V

    rows = V.variance_along_models(spark, sf, ("mlp_nll",), 2, 30, 20).collect()
    spread = {(r["step"], r["sampler"]): r["empirical"] for r in rows}
    assert len(rows) == 4 and all(spread[k, "stratified"] < 0.7 * spread[k, "uniform"] for k in {r["step"] for r in rows})


def test_first_hits_on_the_toy(spark, sf):
    from stratafit.plans import workload_queries as V

    got = {(r["method"], r["epsilon"]): r for r in V.toy_first_hits(spark, sf, (1.0, 0.5), 4000, 2).collect()}
    assert all(got[m, 1.0]["grad_evals"] <= got[m, 0.5]["grad_evals"] for m, e in got if e == 0.5)
    assert got["anchored_stratified", 1.0]["runs"] == 2


def test_large_datasets_write_places_and_points_but_no_examples(spark, sf):
    from pathlib import Path

    from pyspark.sql import functions as F

    from stratafit.operators import series
    from stratafit.plans import workload_queries as V

    folder = Path(spark.sparkContext.getCheckpointDir().removeprefix("file:"))
    size = lambda: sum(f.stat().st_size for f in folder.rglob("*") if f.is_file())
    before = size()
    data = V.dataset(spark, sf, "suppliers", 0)
    points = series.scaled_by_mean(series.daily_by_supplier(spark, sf)).checkpoint()
    whole = {(tuple(r["context"]), tuple(r["target"])) for r in series.segments(points, 72, 24).collect()}
    assert data.arrays is None and size() - before < len(whole) * 96 * 8
    train, test = ([(tuple(r["context"]), tuple(r["target"])) for r in x.collect()] for x in (data.train, data.test))
    assert len(train) + len(test) == len(whole) and set(train) | set(test) == whole and train and test
    # Places give the values of the same examples, in order of series and tick.
    placed = [(tuple(r["context"]), tuple(r["target"])) for r in data.segments(data.index, True).orderBy("gpos").collect()]
    assert set(placed) == set(train) and len(placed) == len(train) == data.strata.agg(F.sum("n")).first()[0]
    ticks = points.select("series_id", "t", F.row_number().over(series.in_order()).alias("i")).filter("i >= 72")
    last = points.agg(F.max("t")).first()[0]
    known = ticks.filter(F.col("t") + 24 < int(0.8 * last)).join(data.index.select("series_id", (F.col("t0") + 1).cast("int").alias("i")), ["series_id", "i"], "full")
    assert known.filter("t is null or i is null").count() == 0


def test_chunks_of_many_cuts_hold_each_example_once(spark, monkeypatch):
    from stratafit.operators import series
    from stratafit.plans import workload_queries as V

    monkeypatch.setattr(V, "CHUNK", 7)
    points = spark.createDataFrame([(s, t * 3, float(t + at)) for s, n, at in (("a", 60, 0), ("b", 9, 100), ("c", 8, 200)) for t in range(n)], "series_id string, t long, z double")
    data = V.split_dataset(points, strata.PerSeries(), 5, 3, 80)
    whole = {(tuple(r["context"]), tuple(r["target"])): r["t0"] + 3 < 80 for r in series.segments(points, 5, 3).collect()}
    for found, own in ((data.train, True), (data.test, False), (data.segments(data.index, False), True)):
        rows = [(tuple(r["context"]), tuple(r["target"])) for r in found.collect()]
        assert sorted(rows) == sorted(k for k, v in whole.items() if v == own)


@pytest.fixture(scope="module")
def fewer(spark, sf, tmp_path_factory):
    """The tables with two of three events and orders."""
    folder = tmp_path_factory.mktemp("fewer")
    for name, key in (("events", "event_id"), ("orders", "o_orderkey")):
        spark.read.parquet(f"{sf}/{name}.parquet").filter(f"{key} % 3 > 0").write.parquet(f"{folder}/{name}.parquet")
    return str(folder)


@pytest.mark.parametrize("name", [
    "counterexample_variance",
    "toy_variance_wrong_step",
    "toy_variance",
    "sampler_variance",
    "geometric_lengths",
])
def test_results_follow_the_tables(spark, sf, fewer, name):
    from stratafit.plans import catalogue

    query = catalogue.queries()[name]
    assert sorted(map(tuple, query(spark, sf).collect())) != sorted(map(tuple, query(spark, fewer).collect()))


@pytest.mark.parametrize("name", ["event_families", "family_vectors", "_toy_arrays"])
def test_arrays_of_workloads_follow_the_events(spark, sf, fewer, name):
    from stratafit.plans import workload_queries as V

    make = {"event_families": lambda d: V.event_families(spark, d).arrays["x"], "family_vectors": lambda d: V.family_vectors(spark, d)["x"], "_toy_arrays": lambda d: V._toy_arrays(spark, d)[0]}[name]
    here, there = make(sf), make(fewer)
    assert np.isfinite(here).all() and (here.shape != there.shape or np.abs(here - there).max() > 1e-6)


def test_stationarity_and_spread_follow_the_events(spark, sf, fewer):
    from stratafit.plans import workload_queries as V

    for make in (lambda d: V.toy_stationarity(spark, d, (0.01,), 400, 1), lambda d: V.variance_along_training(spark, d, 1)):
        assert sorted(map(tuple, make(sf).collect())) != sorted(map(tuple, make(fewer).collect()))
