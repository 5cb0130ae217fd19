"""The experiment workloads: training curves, equal-budget comparison, stationarity by step size, sampler variance along training.

Fits on small datasets run as Spark tasks, one fit each, over arrays that every task gets by broadcast, of ARRAY_BYTES at most; fits on larger ones run over Spark jobs
on all examples, with the same draws.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.models.arrow_kernel import evaluate_chunks
from stratafit.models.forecasters import Forecaster, LSTMModel, MLPModel, ResidualStackModel, VARModel, mse_loss
from stratafit.operators import measures, sampling, series, strata
from stratafit.operators.prepared import prepared
from stratafit.optim import loop
from stratafit.optim.problems import ArrayProblem, SegmentProblem
from stratafit.optim.rules import make_rule
from stratafit.plans.catalogue import register
from stratafit.plans.training_queries import event_toy_examples
from stratafit.sources import synthetic

#: Bytes of a dataset's segments up to which fits run on arrays, one fit a task; beyond, each fit runs over Spark jobs on all examples.
ARRAY_BYTES = 64 << 20
#: Points of a chunk of a dataset's series, halo aside.
CHUNK = 1024
#: method -> (update rule, anchor or none)
METHODS = {
    "sgd": ("sgd", None), "batch_anchor": ("sgd", "batch"), "anchored_stratified": ("sgd", "stratified"), "adam": ("adam", None), "anchored_adam": ("adam", "stratified"), "adagrad": ("adagrad", None), "anchored_adagrad": ("adagrad", "stratified"),
}
STEPS = {"sgd": (0.003, 0.01, 0.03), "adam": (0.001, 0.003, 0.01), "adagrad": (0.01, 0.03, 0.1)}


@dataclass
class Dataset:
    """Training and test examples, cut from chunks when they are read: index places the training ones (stratum, pos, gpos, series_id, t0) in strata. t0 counts a series'
    points here. Chunks of both kinds hold the values whose windows are the examples; and arrays of the same, if small."""

    index: DataFrame
    strata: DataFrame
    chunks: DataFrame
    train_chunks: DataFrame
    test_chunks: DataFrame
    tau_c: int
    tau_p: int
    arrays: dict[str, np.ndarray] | None

    @property
    def train(self) -> DataFrame:
        return series.chunk_segments(self.train_chunks, CHUNK, self.tau_c, self.tau_p)

    @property
    def test(self) -> DataFrame:
        return series.chunk_segments(self.test_chunks, CHUNK, self.tau_c, self.tau_p)

    def segments(self, rows: DataFrame, few: bool) -> DataFrame:
        return series.segments_at(rows, self.chunks, CHUNK, self.tau_c, self.tau_p, few)


def split_dataset(points: DataFrame, policy: strata.Policy, tau_c: int, tau_p: int, cutoff: int | None = None, most: int = ARRAY_BYTES) -> Dataset:
    """Training examples are those whose whole target is before the cutoff, or before four fifths of the span. No example is left out at any size.

    Points are written once, and of the examples only their places: their values, tau_c + tau_p times the points, never are.
    """
    ordered = series.in_order()
    ends = {"i": (F.row_number().over(ordered) - 1).cast("long"), "_ahead": F.lead("t", tau_p).over(ordered).isNotNull()}
    points = prepared(points.withColumn("z", F.col("z").cast("double")).withColumns(ends))
    if cutoff is None:
        cutoff = int(0.8 * points.agg(F.max("t")).first()[0])
    examples = points.filter(F.col("_ahead") & (F.col("i") >= tau_c - 1)).drop("z", "_ahead").withColumnRenamed("t", "t0")
    placed, table = strata.layout(policy.assign(examples).filter(F.col("t0") + tau_p < cutoff))
    index, table = prepared(placed.select("stratum", "pos", "gpos", "series_id", F.col("i").alias("t0"))), prepared(table)
    known = points.groupBy("series_id").agg(F.count_if(F.col("t") + tau_p < cutoff).alias("_known"))
    cut = series.chunk_series(points.select("series_id", F.col("i").alias("t"), "z"), CHUNK, tau_c + tau_p - 1)
    chunks = prepared(cut.join(known, "series_id"))
    # A context ends before the series' first _known points do, or it is a test example's.
    own = F.greatest(F.lit(0), F.col("_known") - F.col("t_first")).cast("int")
    skipped = F.greatest(F.lit(0), own - (tau_c - 1))
    train = chunks.withColumn("values", F.slice("values", F.lit(1), F.when(own > 0, own + tau_p).otherwise(F.lit(0))))
    test = chunks.withColumns({"t_first": F.col("t_first") + skipped, "values": F.slice("values", skipped + 1, F.size("values"))})
    data = Dataset(index, table, chunks, train, test, tau_c, tau_p, None)
    if examples.count() * (tau_c + tau_p) * 8 <= most:
        first, rest = data.segments(index, False).orderBy("gpos").toPandas(), data.test.toPandas()
        pack = lambda frame, name: np.array(frame[name].tolist()).reshape(len(frame), -1)
        data.arrays = {"x": pack(first, "context"), "y": pack(first, "target"), "stratum": first["stratum"].to_numpy(), "test_x": pack(rest, "context"), "test_y": pack(rest, "target")}
    return data


def dataset(spark: SparkSession, d: str, name: str, most: int = ARRAY_BYTES) -> Dataset:
    """shares: hourly values in [0, 1], 72/24, weekday by seven ranges. rates: the nations' daily series, 8/1, six ranges then series. clients: hourly sums of user buckets, 72/24, weekday by ten
    ranges. suppliers: daily sums of every supplier, 72/24, weekday by ten ranges. carrier: the hourly season, 24/6, hours."""
    if name == "shares":
        points, tau, policy = series.hourly_share(spark, d), (72, 24), strata.WeekdaySeason(7, "hour")
    elif name == "rates":
        points, tau, policy = series.scaled_by_mean(series.daily_by_nation(spark, d)), (8, 1), strata.RangeThenSeries(6)
    elif name == "clients":
        points, tau, policy = series.scaled_by_mean(series.hourly_by_bucket(spark, d)), (72, 24), strata.WeekdaySeason(10, "hour")
    elif name == "suppliers":
        points, tau, policy = series.scaled_by_mean(series.daily_by_supplier(spark, d)), (72, 24), strata.WeekdaySeason(10)
    elif name == "carrier":
        points, tau, policy = synthetic.carrier(series.hourly_by_type(spark, d)), (24, 6), strata.CalendarHash(["hour"], "hour")
    else:
        raise ValueError(f"unknown dataset {name}")
    return split_dataset(points, policy, *tau, most=most)


def make_model(kind: str, tau_c: int, tau_p: int, published: bool = False) -> Forecaster:
    """A small network of the kind, or one of the published size."""
    if kind == "var_mse":
        return VARModel(tau_c // tau_p, tau_p, mse_loss)
    if published:
        return {"mlp_nll": MLPModel, "residual_stack_mape": ResidualStackModel, "lstm_mse": LSTMModel}[kind](tau_c, tau_p)
    return {"mlp_nll": lambda: MLPModel(tau_c, tau_p, 16, 2), "residual_stack_mape": lambda: ResidualStackModel(tau_c, tau_p, 2, 16, 2), "lstm_mse": lambda: LSTMModel(tau_c, tau_p, 8, 1, mse_loss)}[kind]()


@dataclass
class Task:
    """One fit: which model by which method, and what ends it."""

    kind: str
    method: str
    lr: float
    seed: int = 0
    grad_evals: int | None = None
    updates: int | None = None
    seconds: float | None = None
    minibatch: int = 8
    published: bool = False

    def run(self, problem, start: np.ndarray, strata_count: int, evaluate=None) -> loop.FitResult:
        budget, rule = loop.Budget(self.seconds, self.grad_evals, self.updates), make_rule(METHODS[self.method][0], self.lr)
        most = self.grad_evals or (self.updates or 10_000) * 100
        if METHODS[self.method][1] is None:
            return loop.minibatch_fit(problem, rule, [(0, k) for k in range(self.updates or self.grad_evals or most)], start, budget, evaluate, self.method, str(self.seed))
        lengths = sampling.inner_lengths(min(10_000, most // strata_count + 1), strata_count, self.seed)
        return loop.anchored_fit(problem, rule, lengths, start, budget=budget, evaluate=evaluate, method=self.method, run=str(self.seed))


def array_fit(data: dict[str, np.ndarray], task: Task, curve: bool = False) -> tuple[loop.FitResult, float, float]:
    """The fit, its training and its test loss over the whole sets."""
    x, y = data["x"], data["y"]
    model = make_model(task.kind, x.shape[1], y.shape[1], task.published)
    problem = ArrayProblem(lambda i, th: model.loss_grad(th, x[i], y[i])[1], len(x), model.size, data["stratum"], task.minibatch, 1, task.seed, METHODS[task.method][1] or "stratified", shared_draws=True)
    both = lambda th: (model.loss_only(th, x, y), model.loss_only(th, data["test_x"], data["test_y"]) if len(data["test_x"]) else float("nan"))
    fit = task.run(problem, model.start(task.seed), len(problem.groups), (lambda th: dict(zip(("train_loss", "test_loss"), both(th), strict=True))) if curve else None)
    return fit, *both(fit.theta)


def spark_fit(data: Dataset, task: Task) -> tuple[loop.FitResult, float, float]:
    """The same fit, of the same draws, with anchors and losses by Spark jobs over all examples."""
    model = make_model(task.kind, data.tau_c, data.tau_p, task.published)
    count = data.strata.count()
    # Plain methods have one endless outer step; its minibatches come in pieces of so many updates.
    anchor = METHODS[task.method][1]
    piece = task.updates or (task.grad_evals or 10_000 * task.minibatch) // task.minibatch + 1
    lengths = [piece] if anchor is None else sampling.inner_lengths(min(10_000, (task.grad_evals or (task.updates or 10_000) * 100) // count + 1), count, task.seed)
    problem = SegmentProblem(model, data.index, data.strata, lengths, task.minibatch, 1, task.seed, anchor or "stratified", segments=data.segments)
    fit = task.run(problem, model.start(task.seed), count)
    train, test = (evaluate_chunks(c, CHUNK, model, fit.theta, data.tau_c, data.tau_p) for c in (data.train_chunks, data.test_chunks))
    return fit, train, test


def equal_budget_table(
    spark: SparkSession, d: str, datasets=("shares", "rates", "clients"), models=("mlp_nll", "residual_stack_mape"), runs: int = 5, grad_evals: int | None = 2000, tuned: bool = True, updates: int | None = None,
    minibatch: int = 8, seconds: float | None = None, published: bool = False, most: int = ARRAY_BYTES,
) -> DataFrame:
    """dataset, model, method, lr, runs, and mean and deviation of training and test loss and of example gradients, at an equal number of example gradients,
    of updates, or of seconds, where these are given instead.

    With tuned, each method takes the step size of its grid with the least mean training loss; otherwise the middle one. Datasets of at most the given bytes are fitted one fit a
    task; larger ones one after the other, each over Spark jobs.
    """
    data = {name: dataset(spark, d, name, most) for name in datasets}
    small = {k: spark.sparkContext.broadcast(v.arrays) for k, v in data.items() if v.arrays is not None}
    grid = [(k, m, method, float(lr), run) for k in datasets for m in models for method, (rule, _) in METHODS.items() for lr in (STEPS[rule] if tuned else STEPS[rule][1:2]) for run in range(runs)]
    limits = {"grad_evals": grad_evals, "updates": updates, "seconds": seconds, "minibatch": minibatch, "published": published}

    def fits(pdf: pd.DataFrame) -> pd.DataFrame:
        r = pdf.iloc[0]
        fit, train, test = array_fit(small[r["dataset"]].value, Task(r["model"], r["method"], r["lr"], int(r["run"]), **limits))
        return pdf.assign(grad_evals=fit.trace.grad_evals, train_loss=train, test_loss=test)

    keys, kinds = ["dataset", "model", "method", "lr", "run"], "dataset string, model string, method string, lr double, run int"
    shared = [g for g in grid if g[0] in small]
    frame = spark.createDataFrame(shared, kinds).repartition(max(1, min(len(shared), 4 * spark.sparkContext.defaultParallelism)), *keys)
    rows = frame.groupBy(*keys).applyInPandas(fits, f"{kinds}, grad_evals long, train_loss double, test_loss double")
    large = []
    for k, m, method, lr, run in grid:
        if k not in small:
            fit, train, test = spark_fit(data[k], Task(m, method, lr, run, **limits))
            large.append((k, m, method, lr, run, fit.trace.grad_evals, train, test))
    if large:
        rows = rows.unionByName(spark.createDataFrame(large, f"{kinds}, grad_evals long, train_loss double, test_loss double"))
    per = rows.groupBy("dataset", "model", "method", "lr").agg(F.count(F.lit(1)).alias("runs"), F.avg("grad_evals").alias("grad_evals"), *[f(c).alias(f"{c}_{n}") for c in ("train_loss", "test_loss") for n, f in (("mean", F.avg), ("std", F.stddev_samp))])
    best = F.struct(F.isnan("train_loss_mean").alias("odd"), F.col("train_loss_mean"), F.col("lr"))
    return per.groupBy("dataset", "model", "method").agg(F.min_by(F.struct("lr", "runs", "grad_evals", "train_loss_mean", "train_loss_std", "test_loss_mean", "test_loss_std"), best).alias("r")).select("dataset", "model", "method", "r.*")


def training_curves(spark: SparkSession, data: dict[str, np.ndarray], kind: str, methods=tuple(METHODS), top: dict[str, int] | None = None, grad_evals: int = 600, minibatch: int = 8) -> DataFrame:
    """method, lr, update, grad_evals, seconds, train_loss, test_loss: the curves by updates, example gradients and time.

    Each method runs with every step size of its grid; kept are its best by final training loss, as many as top says, otherwise one.
    """
    shared = spark.sparkContext.broadcast(data)
    grid = [(m, float(lr)) for m in methods for lr in STEPS[METHODS[m][0]]]
    columns = ["method", "lr", "update", "grad_evals", "seconds", "train_loss", "test_loss"]

    def fits(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for r in pdf.itertuples():
                fit, _, _ = array_fit(shared.value, Task(kind, r.method, r.lr, 0, grad_evals, minibatch=minibatch), curve=True)
                yield pd.DataFrame([(r.method, r.lr, i, x["grad_evals"], x["seconds"], x["train_loss"], x["test_loss"]) for i, x in enumerate(fit.trace.rows)], columns=columns)

    curves = prepared(spark.createDataFrame(grid, "method string, lr double").repartition(len(grid)).mapInPandas(fits, "method string, lr double, update int, grad_evals long, seconds double, train_loss double, test_loss double"))
    final = curves.groupBy("method", "lr").agg(F.max_by("train_loss", "update").alias("last"))
    place = F.row_number().over(W.Window.partitionBy("method").orderBy(F.isnan("last"), "last", "lr"))
    wanted = F.coalesce(*[F.when(F.col("method") == m, F.lit(n)) for m, n in (top or {}).items()], F.lit(1))
    return curves.join(final.withColumn("place", place).filter(F.col("place") <= wanted).select("method", "lr"), ["method", "lr"]).select(columns)


def families(spark: SparkSession, k: int = 4, n: int = 400, tau_c: int = 12, tau_p: int = 3) -> Dataset:
    """Segments of transformed ramps; the family is the true stratum."""
    spark.dataSource.register(synthetic.SyntheticFamilies)
    points = spark.read.format("synthetic_families").option("families", k).option("n", n).load()
    return split_dataset(points, strata.GivenStratum("family"), tau_c, tau_p, int(0.8 * n))


def event_families(spark: SparkSession, d: str, tau_c: int = 12, tau_p: int = 3) -> Dataset:
    """The same of the hourly events: each type is a family."""
    return split_dataset(synthetic.families_on(series.hourly_by_type(spark, d)), strata.GivenStratum("family"), tau_c, tau_p)


def family_vectors(spark: SparkSession, d: str, lags: int = 2, delays: Sequence[int] = (0, 5, 11)) -> dict[str, np.ndarray]:
    """Vectors of a family's values seen at several delays: contexts of the last lags vectors, newest first, and the next vector as target."""
    data = event_families(spark, d, max(delays) + lags, 1).arrays
    both = lambda x, y: (np.stack([x[:, -1 - s - j] for j in range(lags) for s in delays], axis=1), np.stack([y[:, 0] if s == 0 else x[:, -s] for s in delays], axis=1))
    (x, y), (tx, ty) = both(data["x"], data["y"]), both(data["test_x"], data["test_y"])
    return {"x": x, "y": y, "stratum": data["stratum"], "test_x": tx, "test_y": ty}


def _toy_arrays(spark: SparkSession, d: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The examples of the toy's season on the hourly events: as many as types and hours, whatever the number of events."""
    pdf = event_toy_examples(spark, d).orderBy("series_id", "t0").toPandas()
    return pdf[["x1", "x2"]].to_numpy(), pdf["y"].to_numpy(), pdf["t0"].to_numpy() % 8


def toy_first_hits(spark: SparkSession, d: str, epsilons=(1.0, 0.5, 0.25), grad_evals: int = 12_000, seeds: int = 4, lr: float = 0.003) -> DataFrame:
    """method, epsilon, runs, grad_evals: the mean number of example gradients after which a run's gradient norm first is at most epsilon on the toy."""
    shared = spark.sparkContext.broadcast(_toy_arrays(spark, d))
    grid = [(m, s) for m in ("sgd", "batch_anchor", "anchored_stratified", "full_anchor") for s in range(seeds)]

    def fits(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x, y, labels = shared.value
        a, c = x.T @ x / len(y), x.T @ y / len(y)
        for frame in batches:
            for r in frame.itertuples():
                fit = _toy_fit(x, y, labels, r.method, lr, r.seed, grad_evals, lambda th: {"grad_norm": float(np.linalg.norm(2 * (a @ th - c)))})
                rows, least = [], np.inf
                for row in fit.trace.rows:  # a first hit is a new least norm
                    if row["grad_norm"] < least:
                        least = row["grad_norm"]
                        rows.append((r.method, str(r.seed), row["grad_evals"], least))
                yield pd.DataFrame(rows, columns=["method", "run", "grad_evals", "grad_norm"])

    trace = prepared(spark.createDataFrame(grid, "method string, seed int").repartition(len(grid)).mapInPandas(fits, "method string, run string, grad_evals long, grad_norm double"))
    out = None
    for epsilon in epsilons:
        one = measures.first_hit(trace, epsilon).groupBy("method").agg(F.lit(float(epsilon)).alias("epsilon"), F.count(F.lit(1)).alias("runs"), F.avg("grad_evals").alias("grad_evals"))
        out = one if out is None else out.unionByName(one)
    return out


def _toy_fit(x, y, labels, method: str, lr: float, seed: int, grad_evals: int, evaluate) -> loop.FitResult:
    gradient = lambda i, th: (2 * (x[i] @ th - y[i])[:, None] * x[i]).mean(axis=0)
    budget, rule = loop.Budget(grad_evals=grad_evals), make_rule("sgd", lr)
    kind = {"batch_anchor": "batch", "full_anchor": "full"}.get(method, "stratified")
    problem = ArrayProblem(gradient, len(y), 2, labels, 1, 1, seed, kind)
    if method == "sgd":
        return loop.minibatch_fit(problem, rule, [(0, k) for k in range(grad_evals)], budget=budget, evaluate=evaluate)
    law = ("fixed", len(y) // 2) if kind == "full" else ("geometric", 1)
    return loop.anchored_fit(problem, rule, sampling.inner_lengths(2000, 8, seed, law[0], law[1]), budget=budget, evaluate=evaluate)


def toy_stationarity(spark: SparkSession, d: str, lrs=(0.001, 0.003, 0.01), grad_evals: int = 12_000, seeds: int = 4) -> DataFrame:
    """method, lr, tail: mean squared gradient norm over the last fifth of the updates on the period-8 toy, at equal example gradients."""
    shared = spark.sparkContext.broadcast(_toy_arrays(spark, d))
    grid = [(m, float(lr), s) for m in ("sgd", "batch_anchor", "anchored_stratified", "full_anchor") for lr in lrs for s in range(seeds)]

    def fits(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x, y, labels = shared.value
        a, c = x.T @ x / len(y), x.T @ y / len(y)
        for frame in batches:
            for r in frame.itertuples():
                norms: list[float] = []
                _toy_fit(x, y, labels, r.method, r.lr, r.seed, grad_evals, lambda th: norms.append(float(((2 * (a @ th - c)) ** 2).sum())) or {})  # noqa: B023
                yield pd.DataFrame([(r.method, r.lr, r.seed, float(np.mean(norms[-max(1, len(norms) // 5) :])))], columns=["method", "lr", "seed", "tail"])

    frame = spark.createDataFrame(grid, "method string, lr double, seed int").repartition(min(len(grid), 32))
    rows = frame.mapInPandas(fits, "method string, lr double, seed int, tail double")
    return rows.groupBy("method", "lr").agg(F.avg("tail").alias("tail"), F.count(F.lit(1)).alias("runs"))


def variance_along_training(spark: SparkSession, d: str, points: int = 5) -> DataFrame:
    """step, sampler, draws, empirical: spread of the samplers at points of an anchored run on the toy, uniform against strata of period 8."""
    ex = event_toy_examples(spark, d)
    x, y, labels = _toy_arrays(spark, d)
    problem = ArrayProblem(lambda i, th: (2 * (x[i] @ th - y[i])[:, None] * x[i]).mean(axis=0), len(y), 2, labels)
    fit = loop.anchored_fit(problem, make_rule("sgd", 0.01), [8] * 40)
    assigned = strata.ModPeriod(8).assign(ex)
    out = None
    for k in np.linspace(0, len(fit.trace.rows) - 1, points).astype(int).tolist():
        one = measures.sampler_variance(assigned, tuple(fit.trace.rows[k]["theta"]), 100, 1, 17).select(F.lit(k).alias("step"), "sampler", "draws", F.round("empirical", 6).alias("empirical"))
        out = one if out is None else out.unionByName(one)
    return out


def variance_along_models(spark: SparkSession, d: str, kinds=("mlp_nll", "residual_stack_mape"), points: int = 4, repeats: int = 60, updates: int = 120) -> DataFrame:
    """model, step, sampler, draws, empirical: mean squared distance of repeated estimates from the full gradient at points of an anchored run of each
    network on the hourly carrier, uniform against strata of hours, at equal draws."""
    shared = spark.sparkContext.broadcast(dataset(spark, d, "carrier").arrays)
    columns = ["model", "step", "sampler", "draws", "empirical"]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x, y, labels = (shared.value[k] for k in ("x", "y", "stratum"))
        for frame in batches:
            for r in frame.itertuples():
                model = make_model(r.model, x.shape[1], y.shape[1])
                problem = ArrayProblem(lambda i, th: model.loss_grad(th, x[i], y[i])[1], len(x), model.size, labels, 8, shared_draws=True)  # noqa: B023
                thetas = [model.start(0)]
                Task(r.model, "anchored_adam", 0.003, updates=updates).run(problem, thetas[0], len(problem.groups), lambda th: thetas.append(th.copy()) or {})  # noqa: B023
                rng, n = np.random.default_rng(5), len(problem.groups)
                for k in np.linspace(0, len(thetas) - 1, points).astype(int).tolist():
                    full = problem.gradient(np.arange(len(x)), thetas[k])
                    found = {"uniform": [problem.gradient(rng.integers(0, len(x), n), thetas[k]) for _ in range(repeats)], "stratified": [problem.anchor(10**6 + j, thetas[k])[0] for j in range(repeats)]}
                    yield pd.DataFrame([(r.model, k, s, n, float(np.mean([((g - full) ** 2).sum() for g in v]))) for s, v in found.items()], columns=columns)

    return spark.createDataFrame([(k,) for k in kinds], "model string").repartition(len(kinds)).mapInPandas(run, "model string, step int, sampler string, draws int, empirical double")


def vector_curves(spark: SparkSession, d: str) -> DataFrame:
    """Vector autoregression over the regions' daily sales by SGD, batch anchor and strata of calendar years: method, lr, update, grad_evals, seconds, train_loss, test_loss."""
    points = series.scaled_by_mean(series.daily_by_region(spark, d)).withColumn("year", F.year(F.date_add(F.lit("1970-01-01").cast("date"), F.col("bucket").cast("int"))))
    # One row a day, whatever the number of orders.
    pdf = points.groupBy("t").agg(F.first("year").alias("year"), F.array_sort(F.collect_list(F.struct("series_id", "z"))).alias("v")).select("t", "year", F.col("v.z").alias("z")).orderBy("t").toPandas()
    z, year = np.array(pdf["z"].tolist()), pdf["year"].to_numpy()
    x, y, cut = np.concatenate([z[1:-1], z[:-2]], axis=1), z[2:], int(0.8 * (len(z) - 2))
    data = {"x": x[:cut], "y": y[:cut], "stratum": year[2:][:cut] - year.min(), "test_x": x[cut:], "test_y": y[cut:]}
    return training_curves(spark, data, "var_mse", ("sgd", "batch_anchor", "anchored_stratified"), {"sgd": 3}, 1200, 4)


_PLAIN = ("sgd", "batch_anchor", "anchored_stratified")
register("workload_equal_budget", lambda s, d: equal_budget_table(s, d, grad_evals=5000))
register("workload_equal_updates", lambda s, d: equal_budget_table(s, d, ("carrier",), ("mlp_nll",), 3, None, True, 400, 1))
register("workload_equal_seconds", lambda s, d: equal_budget_table(s, d, ("carrier",), ("mlp_nll",), 5, None, False, seconds=1.0))
register("workload_many_series", lambda s, d: equal_budget_table(s, d, ("suppliers",), ("mlp_nll",), 1, 1500, False))
register("workload_carrier_curves", lambda s, d: training_curves(s, dataset(s, d, "carrier").arrays, "mlp_nll", grad_evals=800))
register("workload_families_lstm", lambda s, d: training_curves(s, event_families(s, d).arrays, "lstm_mse", _PLAIN, {"sgd": 3}, 200))
register("workload_families_var", lambda s, d: training_curves(s, family_vectors(s, d), "var_mse", _PLAIN, {"sgd": 3}, 2000, 4))
register("workload_vector_curves", vector_curves)
register("workload_toy_stationarity", toy_stationarity)
register("workload_toy_first_hits", toy_first_hits)
register("workload_variance_along_training", variance_along_training)
register("workload_variance_along_models", variance_along_models)
