import duckdb
import pytest

import __spark_entry__ as entry_module
from stratafit.plans import catalogue
from stratafit.streaming import feeds
from verify_sql import TABLES, differences

NAMES = sorted(catalogue.oracle_sql())


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf, con, name):
    got = catalogue.queries()[name](spark, sf).toPandas()
    assert not (what := differences(got, con.execute(catalogue.oracle_sql()[name]).df())), what


def test_entry(spark):
    rows = entry_module.entry(spark).collect()
    shares = {(r["workload"], r["policy"]): r["within_share"] for r in rows}
    assert shares["toy", "mod8"] < 0.15 and shares["carrier", "hour"] < 0.1 and shares["carrier", "weekday"] > 0.98


def test_published_counts_of_strata(spark, sf):
    assert catalogue.queries()["strata_weekday_year"](spark, sf).count() == 49
    assert catalogue.queries()["strata_weekday_ranges10"](spark, sf).count() == 70


def test_streams(spark, sf):
    from pyspark.sql import functions as F

    events = spark.read.parquet(f"{sf}/events.parquet")
    closed = feeds.run_once(feeds.hourly_cents(feeds.events_stream(spark, sf)), "closed_hours")
    every = events.groupBy(F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("start"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    assert 0.95 * every.count() < closed.count() <= every.count()
    once = feeds.run_once(feeds.first_events(feeds.events_stream(spark, sf)), "once")
    assert once.count() == events.select("event_id").distinct().count()
    assert feeds.run_once(feeds.sliding_counts(feeds.events_stream(spark, sf)), "sliding", "complete").agg(F.sum("n")).first()[0] == 2 * events.count()
    assert feeds.run_once(feeds.sessions(feeds.events_stream(spark, sf)), "sessions", "append").agg(F.sum("n")).first()[0] <= events.count()
    seen = []
    feeds.refresh_anchor(feeds.events_stream(spark, sf), lambda batch, k: seen.append(batch.count())).awaitTermination()
    assert sum(seen) == events.count()
    alarm = feeds.drift_alarm(spark.createDataFrame([(0, 0.1), (1, 0.9)], "batch int, within_share double"), 0.5).collect()
    assert [r["alarm"] for r in alarm] == [False, True]


def test_core_does_not_import_the_subpackage():
    import pathlib

    root = pathlib.Path(entry_module.__file__).parent / "stratafit"
    for path in root.rglob("*.py"):
        if "llm" not in path.parts:
            assert "llm" not in path.read_text(), path
