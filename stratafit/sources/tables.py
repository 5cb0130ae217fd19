"""Reading the given tables and the synthetic series."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(amount: Column) -> Column:
    """Money as whole cents, so that sums are exact in any order."""
    return F.round(amount * 100).cast("long")


def day_number(ts: Column) -> Column:
    """Days since 1970-01-01; no session time zone takes part."""
    return F.datediff(ts, F.lit("1970-01-01").cast("date")).cast("long")


def hour_number(ts: Column) -> Column:
    return day_number(ts) * 24 + F.hour(ts).cast("long")


def month_number(ts: Column) -> Column:
    return ((F.year(ts) - 1970) * 12 + F.month(ts) - 1).cast("long")


CLOCKS = {"hour": hour_number, "day": day_number, "month": month_number}
