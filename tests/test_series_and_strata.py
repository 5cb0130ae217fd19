import numpy as np
import pytest
from pyspark.sql import functions as F

from stratafit.operators import sampling, series, strata, table_functions
from stratafit.functions import portable
from stratafit.sources import synthetic


def points(spark, lengths):
    rows = [(s, t, t, float((7 * t + 3 * k) % 11 - 5)) for k, (s, n) in enumerate(lengths.items()) for t in range(n)]
    return spark.createDataFrame(rows, "series_id string, t long, bucket long, z double")


def test_gap_fill(spark):
    df = spark.sql("select * from values ('a', timestamp_ntz'2024-01-01 00:10:00', 2.0), ('a', timestamp_ntz'2024-01-01 00:50:00', 3.0), ('a', timestamp_ntz'2024-01-01 03:00:00', 4.0), ('b', timestamp_ntz'2024-01-01 01:00:00', 1.0) as v(s, ts, v)")
    make = lambda fill: {(r["series_id"], r["t"]): r["z"] for r in series.regularize(df, F.col("s"), F.col("ts"), F.sum("v"), "hour", fill).collect()}
    assert make("zero") == {("a", 0): 5, ("a", 1): 0, ("a", 2): 0, ("a", 3): 4, ("b", 0): 0, ("b", 1): 1, ("b", 2): 0, ("b", 3): 0}
    assert make("ffill") == {("a", 0): 5, ("a", 1): 5, ("a", 2): 5, ("a", 3): 4, ("b", 1): 1, ("b", 2): 1, ("b", 3): 1}
    assert make("drop") == {("a", 0): 5, ("a", 3): 4, ("b", 1): 1}
    with pytest.raises(ValueError):
        make("guess")


@pytest.mark.parametrize("tau_c,tau_p", [(2, 1), (5, 3), (8, 4)])
def test_segments_counts_and_chunks(spark, tau_c, tau_p):
    p = points(spark, {"a": 40, "b": tau_c + tau_p - 1, "c": tau_c + tau_p, "d": 1})
    plain = sorted(map(tuple, series.segments(p, tau_c, tau_p).collect()))
    index = {r["series_id"]: r["n_examples"] for r in series.example_index(p, tau_c, tau_p).collect()}
    assert index == {"a": 40 - tau_c - tau_p + 1, "b": 0, "c": 1, "d": 0} and len(plain) == sum(index.values())
    for chunk in (1, 7, 16, 64):
        chunks = series.chunk_series(p, chunk, tau_c + tau_p - 1)
        assert sorted(map(tuple, series.chunk_segments(chunks, chunk, tau_c, tau_p).collect())) == plain
    name, t0, context, target = plain[3]
    z = {r["t"]: r["z"] for r in p.filter(F.col("series_id") == name).collect()}
    assert context == [z[t0 - tau_c + 1 + i] for i in range(tau_c)] and target == [z[t0 + 1 + i] for i in range(tau_p)]


def test_lags_put_the_newest_first(spark):
    r = series.lag_examples(points(spark, {"a": 6}), 2).orderBy("t0").first()
    z = [float((7 * t) % 11 - 5) for t in range(6)]
    assert (r["t0"], r["y"], r["x1"], r["x2"]) == (1, z[2], z[1], z[0])


def test_split_keeps_targets_apart(spark):
    train, test = series.split_by_time(points(spark, {"a": 30}), 20, 4)
    assert train.agg(F.max("t")).first()[0] == 19
    assert series.lag_examples(test, 4).agg(F.min("t0")).first()[0] == 19


def test_scaling(spark):
    p = points(spark, {"a": 12, "b": 20})
    for kind in ("mean_abs", "max_abs", "zscore"):
        scaled = series.apply_scale(p, series.fit_scale(p, kind))
        z = np.array([r["z"] for r in scaled.filter("series_id = 'b'").collect()])
        assert {"mean_abs": abs(np.abs(z).mean() - 1), "max_abs": abs(np.abs(z).max() - 1), "zscore": abs(z.mean()) + abs(z.std() - 1)}[kind] < 1e-9
    flat = spark.createDataFrame([("a", 0, 0.0)], "series_id string, t long, z double")
    assert series.apply_scale(flat, series.fit_scale(flat)).first()["z"] == 0


POLICIES = [
    strata.ModPeriod(5), strata.PerSeries(), strata.RandomHash(6), strata.Cyclic(7), strata.EqualSize(7), strata.Finest(), strata.CalendarHash(["weekday", "hour"], "hour"), strata.WeekdaySeason(3, "hour"), strata.RangeThenSeries(4),
    strata.Compose([strata.ModPeriod(3), strata.PerSeries()]), strata.MergeSmall(strata.PerSeries(), 20), strata.GivenStratum("bucket"),
]


@pytest.mark.parametrize("policy", POLICIES, ids=lambda p: type(p).__name__)
def test_policies_partition(spark, policy):
    ex = series.lag_examples(points(spark, {"a": 40, "b": 13, "c": 31}), 2)
    placed, table = strata.layout(policy.assign(ex))
    rows, info = placed.collect(), {r["stratum"]: r for r in table.collect()}
    assert len(rows) == ex.count() == len({(r["series_id"], r["t0"]) for r in rows})
    assert sorted(info) == list(range(len(info))) and abs(sum(r["w"] for r in info.values()) - 1) < 1e-12
    for k, r in info.items():
        assert sorted(x["pos"] for x in rows if x["stratum"] == k) == list(range(r["n"]))
    by = sorted(rows, key=lambda r: (r["series_id"], r["t0"]))
    assert [r["gpos"] for r in by] == list(range(len(by)))


def test_sizes_of_dealt_strata(spark):
    ex = series.lag_examples(points(spark, {"a": 40, "b": 13}), 2)
    for policy in (strata.Cyclic(6), strata.EqualSize(6)):
        sizes = [r["n"] for r in strata.stratum_table(policy.assign(ex)).collect()]
        assert max(sizes) - min(sizes) <= 1 and len(sizes) == 6


def test_kmeans_levels(spark):
    rows = [(f"s{k}", t, [float(k % 3) * 10 + t * 0.01, 1.0]) for k in range(9) for t in range(6)]
    df = spark.createDataFrame(rows, "series_id string, t0 long, features array<double>")
    for policy in (strata.KMeansPolicy(3), strata.KMeansPolicy(3, bisecting=True), strata.KMeansPolicy(3, level="series")):
        got = policy.assign(df).collect()
        assert len(got) == 54 and {r["stratum"] for r in got} == {0, 1, 2}
        assert policy.bisecting or len({(int(r["series_id"][1:]) % 3, r["stratum"]) for r in got}) == 3
    few, many = strata.KMeansPolicy(2), strata.KMeansPolicy(5)
    few.assign(df), many.assign(df)
    assert many.inertia <= few.inertia


def test_portable_numbers_agree_with_python(spark):
    row = spark.range(5).select(portable.uniform(7, 0, 3, F.col("id")).alias("u")).collect()
    assert [r["u"] for r in row] == [portable.py_uniform(7, 0, 3, k) for k in range(5)]
    assert int(portable.py_uniform(7, 0, 3, 12) * 2**52) == 2320675542604334


def test_draws_stay_in_their_strata(spark):
    placed, table = strata.layout(strata.PerSeries().assign(series.lag_examples(points(spark, {"a": 40, "b": 13, "c": 4}), 2)))
    info = {r["stratum"]: r["n"] for r in table.collect()}
    draws = sampling.stratified_draws(table, 3, 1).collect()
    assert len(draws) == 9 and all(0 <= r["pos"] < info[r["stratum"]] for r in draws)
    without = sampling.stratified_without_replacement(placed, table, 5, 1).collect()
    assert len(without) == len({(r["stratum"], r["pos"]) for r in without}) == 5 + 5 + 2
    plain = sampling.uniform_draws(spark, 51, 51, 1, replacement=False, examples=placed).collect()
    assert sorted(r["gpos"] for r in plain) == list(range(51))
    again = sampling.stratified_draws(table, 3, 1).collect()
    assert sorted(map(str, draws)) == sorted(map(str, again))


def test_series_then_time_weights_undo_the_bias(spark):
    index = spark.createDataFrame([("a", 100), ("b", 10), ("c", 0)], "series_id string, n_examples long")
    got = sampling.series_then_time_draws(index, 4000, 2, correct=True).collect()
    share = sum(r["weight"] for r in got if r["series_id"] == "a") / 4000
    assert abs(share - 100 / 110) < 0.05 and abs(sum(r["series_id"] == "a" for r in got) / 4000 - 0.5) < 0.03


def test_geometric_lengths():
    for b in (1, 8, 49):
        k = np.array([sampling.geometric_length(b, portable.py_uniform("g", b, i)) for i in range(20_000)])
        assert abs(k.mean() - b) < 3 * np.sqrt(b * (b + 1) / 20_000) and abs((k == 0).mean() - 1 / (b + 1)) < 0.012
    assert sampling.inner_lengths(3, 5, 1, "fixed", 4) == [4, 4, 4]
    assert [sampling.pick_iterate([1, 0, 3], u) for u in (0, 0.2, 0.3, 0.99)] == [0, 0, 2, 2]


def test_weighted_and_bernoulli_draws(spark):
    mass = spark.createDataFrame([(0, 1.0), (1, 3.0)], "stratum int, mass double")
    got = sampling.weighted_draws(mass, 2000, 3).collect()
    assert len(got) == 2000 and abs(np.mean([r["stratum"] for r in got]) - 0.75) < 0.04
    assert abs(np.mean([r["weight"] * (10.0 if r["stratum"] else 2.0) for r in got]) - 6.0) < 0.3
    assert sampling.bernoulli_strata(spark.createDataFrame([(k % 2,) for k in range(100)], "stratum int"), {0: 1.0}, 1).count() == 50


def test_table_functions(spark):
    table_functions.register(spark)
    p = points(spark, {"a": 12, "b": 3})
    p.createOrReplaceTempView("tf_points")
    got = spark.sql("SELECT * FROM segments(TABLE(tf_points) PARTITION BY series_id ORDER BY (t), 3, 2)")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, series.segments(p, 3, 2).collect()))
    _, table = strata.layout(strata.PerSeries().assign(series.lag_examples(p, 2)))
    table.createOrReplaceTempView("tf_strata")
    drawn = spark.sql("SELECT * FROM stratified_draws(TABLE(tf_strata), 3, 5)").select("stratum", "draw", "pos", "w")
    assert sorted(map(tuple, drawn.collect())) == sorted(map(tuple, sampling.stratified_draws(table, 3, 5).collect()))


def test_synthetic_families(spark):
    spark.dataSource.register(synthetic.SyntheticFamilies)
    df = spark.read.format("synthetic_families").option("families", 9).option("n", 50).option("noise", 0).option("slice", 20).load()
    assert df.count() == 450 and df.select("family").distinct().count() == 9
    square = [r["z"] for r in df.filter("family = 3").orderBy("t").collect()]
    assert np.allclose(square, (np.arange(50) / 50) ** 2)
