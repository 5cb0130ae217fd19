"""Joins of values to the spans that hold them, by cells instead of comparing every value with every span."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Cells that the whole range is cut into at least; there are as many as spans where those are more.
CELLS = 4096


def span_join(rows: DataFrame, spans: DataFrame, value: str, width: str) -> DataFrame:
    """rows with the other columns of the span (lo, hi) that holds value, lo <= value < hi.

    Both sides have the column width, the size of a cell. A span is repeated for each cell it touches, so spans that follow one another
    give at most their number plus that of the cells; values meet the spans of their cell only.
    """
    cell = lambda x: F.floor(x / F.col(width)).cast("long")
    cut = spans.withColumn("_cell", F.explode(F.sequence(cell(F.col("lo")), cell(F.col("hi"))))).drop(width)
    held = (F.col(value) >= F.col("lo")) & (F.col(value) < F.col("hi"))
    return rows.withColumn("_cell", cell(F.col(value))).drop(width).join(cut, "_cell").filter(held).drop("_cell", "lo", "hi")


def cell_width(total: Column, spans: Column) -> Column:
    """Of at least 1, for whole numbers up to total."""
    return F.greatest(F.lit(1.0), F.floor(total / F.greatest(F.lit(CELLS), spans)).cast("double"))
