from pyspark.sql import functions as F

from stratafit.operators import series, strata
from stratafit.optim.loop import Trace
from stratafit.sources import sinks
from stratafit.sources.tables import table


def test_round_trips(spark, sf, tmp_path):
    points = series.monthly_by_nation(spark, sf)
    sinks.write_points(points, str(tmp_path / "points"))
    assert sorted(map(str, spark.read.parquet(str(tmp_path / "points")).select(points.columns).collect())) == sorted(map(str, points.collect()))
    assigned = strata.PerSeries().assign(series.lag_examples(points, 2))
    sinks.write_strata(assigned, str(tmp_path / "strata"))
    assert spark.read.parquet(str(tmp_path / "strata")).filter("stratum = 1").count() == assigned.filter("stratum = 1").count()
    chunks = series.chunk_series(points, 16, 9)
    sinks.save_chunks(chunks, "chunk_table", 4)
    joined = spark.table("chunk_table").join(spark.table("chunk_table").select("series_id", "chunk_no"), ["series_id", "chunk_no"])
    assert joined.count() == chunks.count()
    trace = Trace("sgd")
    import numpy as np

    trace.add(0, 0, np.zeros(2), np.ones(2), None)
    for _ in range(2):
        sinks.append_trace(trace.to_df(spark), str(tmp_path / "trace"))
    assert spark.read.parquet(str(tmp_path / "trace")).count() == 2


def test_filters_and_columns_reach_the_scan(spark, sf):
    plan = series._orders_with_nation(spark, sf).filter("n_nationkey < 8")._jdf.queryExecution().executedPlan().toString()
    assert "LessThan(c_nationkey,8)" in plan and "o_comment" not in plan and "CartesianProduct" not in plan
    scan = table(spark, sf, "events").filter(F.col("user_id") == 3).select("value")._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(user_id,3)" in scan and "props" not in scan
