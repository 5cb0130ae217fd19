"""SQL table functions: segments of a table's series, and draws from strata."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf

from stratafit.functions.portable import py_uniform


@udtf(returnType="series_id string, t0 bigint, context array<double>, target array<double>")
class Segments:
    """SELECT * FROM segments(TABLE(points) PARTITION BY series_id ORDER BY (t), tau_c, tau_p): a ring of tau_c + tau_p values per series."""

    def __init__(self) -> None:
        self.ring: list[float] = []

    def eval(self, row: Row, tau_c: int, tau_p: int) -> Iterator[tuple]:
        self.ring.append(float(row["z"]))
        if len(self.ring) > tau_c + tau_p:
            self.ring.pop(0)
        if len(self.ring) == tau_c + tau_p:
            yield str(row["series_id"]), int(row["t"]) - tau_p, self.ring[:tau_c], self.ring[tau_c:]


@udtf(returnType="stratum int, draw int, pos bigint, w double")
class StratifiedDraws:
    """SELECT * FROM stratified_draws(TABLE(strata), per_stratum, seed) over (stratum, n, w): the draws that the DataFrame sampler makes."""

    def eval(self, row: Row, per_stratum: int, seed: int) -> Iterator[tuple]:
        for draw in range(per_stratum):
            u = py_uniform(seed, "stratified", row["stratum"], draw)
            yield int(row["stratum"]), draw, min(int(u * row["n"]), int(row["n"]) - 1), float(row["w"])


def register(spark: SparkSession) -> None:
    spark.udtf.register("segments", Segments)
    spark.udtf.register("stratified_draws", StratifiedDraws)
