"""Gradients and losses of any forecaster over all examples: numpy in Arrow batches, partial sums per task and stratum."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stratafit.models.forecasters import Forecaster
from stratafit.operators.series import chunk_windows

#: Parameters in one row of a partial sum: vectors travel in pieces, so that no row is huge.
PIECE = 65_536


def _arrays(batch: pa.RecordBatch, name: str) -> np.ndarray:
    column = batch.column(name)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)


def gradient_sums(examples: DataFrame, model: Forecaster, theta: np.ndarray, batch: int = 512, squares: bool = False, weighted: bool = False) -> DataFrame:
    """stratum, piece, n, loss, square, grad: sums over the examples (stratum, context, target) of each stratum.

    square sums the squared norms of single examples' gradients (asked for by squares; one pass each), in piece 0.
    With weighted, examples have a weight instead, and losses and gradients are summed over all times it, in stratum 0.
    A task sends one row per stratum and piece, whatever its number of examples.
    """
    shared = examples.sparkSession.sparkContext.broadcast(theta)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, list] = {}
        at = shared.value
        for rows in batches:
            x, y, s = _arrays(rows, "context"), _arrays(rows, "target"), rows.column("label").to_numpy()
            for k in np.unique(s):
                key, scale = (0, float(k)) if weighted else (int(k), 1.0)
                own = np.flatnonzero(s == k)
                for i in range(0, len(own), batch):
                    part = own[i : i + batch]
                    loss, grad = model.loss_grad(at, x[part], y[part])
                    square = sum(float(g @ g) for g in (model.loss_grad(at, x[j : j + 1], y[j : j + 1])[1] for j in part)) if squares else 0.0
                    have = sums.setdefault(key, [0, 0.0, 0.0, 0.0])
                    have[0] += len(part)
                    have[1] += loss * len(part) * scale
                    have[2] += square
                    have[3] = have[3] + grad * (len(part) * scale)
        for k, (n, loss, square, grad) in sums.items():
            for piece in range(0, len(grad), PIECE):
                first = piece == 0
                values = grad[piece : piece + PIECE]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([k], pa.int32()), pa.array([piece // PIECE], pa.int32()), pa.array([n if first else 0], pa.int64()), pa.array([loss if first else 0.0]), pa.array([square if first else 0.0]), pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), pa.array(values))],
                    names=["stratum", "piece", "n", "loss", "square", "grad"],
                )

    label = F.col("weight").cast("double") if weighted else F.col("stratum").cast("int")
    return examples.select(label.alias("label"), "context", "target").mapInArrow(run, "stratum int, piece int, n long, loss double, square double, grad array<double>")


def _added(parts: DataFrame, keys: list[str]) -> DataFrame:
    """Partial sums added up, vectors element by element, in two levels so that no task gets every task's vectors."""

    def run(key: tuple, table: pa.Table) -> pa.Table:
        grads = table["grad"].combine_chunks()
        total = grads.flatten().to_numpy().reshape(table.num_rows, -1).sum(axis=0)
        sums = [pa.array([float(np.sum(table[c].to_numpy()))]) for c in ("loss", "square")]
        row = [pa.array([table["stratum"][0].as_py()], pa.int32()), pa.array([table["piece"][0].as_py()], pa.int32()), pa.array([int(np.sum(table["n"].to_numpy()))], pa.int64()), *sums, pa.ListArray.from_arrays(pa.array([0, len(total)], pa.int32()), pa.array(total))]
        return pa.Table.from_arrays(row, names=["stratum", "piece", "n", "loss", "square", "grad"])

    return parts.groupBy(*keys).applyInArrow(run, "stratum int, piece int, n long, loss double, square double, grad array<double>")


def gradient_by_stratum(examples: DataFrame, model: Forecaster, theta: np.ndarray, squares: bool = False, fan_in: int = 64) -> dict[int, tuple[int, float, np.ndarray, float]]:
    """stratum -> (n, mean loss, mean gradient, mean squared norm)."""
    parts = gradient_sums(examples, model, theta, squares=squares).withColumn("_g", F.pmod(F.spark_partition_id(), F.lit(fan_in)))
    halfway = _added(parts, ["stratum", "piece", "_g"])
    out: dict[int, list] = {}
    for r in _added(halfway, ["stratum", "piece"]).orderBy("stratum", "piece").toLocalIterator():
        have = out.setdefault(r["stratum"], [r["n"], r["loss"], [], r["square"]])
        have[2].append(np.array(r["grad"]))
    return {k: (n, loss / n, np.concatenate(g) / n, sq / n) for k, (n, loss, g, sq) in out.items()}


def weighted_gradient(examples: DataFrame, model: Forecaster, theta: np.ndarray, fan_in: int = 64) -> tuple[np.ndarray, int]:
    """The sum of the examples' gradients times their weight (context, target, weight), and their number: one vector comes to the driver, whatever the strata."""
    parts = gradient_sums(examples, model, theta, weighted=True).withColumn("_g", F.pmod(F.spark_partition_id(), F.lit(fan_in)))
    rows = sorted(_added(_added(parts, ["stratum", "piece", "_g"]), ["stratum", "piece"]).collect(), key=lambda r: r["piece"])
    return (np.concatenate([r["grad"] for r in rows]), rows[0]["n"]) if rows else (np.zeros(model.size), 0)


def evaluate(segments: DataFrame, model: Forecaster, theta: np.ndarray, batch: int = 1024) -> float:
    """Mean loss over all segments."""
    shared = segments.sparkSession.sparkContext.broadcast(theta)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total = 0, 0.0
        for rows in batches:
            x, y = _arrays(rows, "context"), _arrays(rows, "target")
            for i in range(0, len(x), batch):
                part = slice(i, i + batch)
                total += model.loss_only(shared.value, x[part], y[part]) * len(x[part])
            n += len(x)
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([total])], names=["n", "loss"])

    return _mean_loss(segments.select("context", "target").mapInArrow(run, "n long, loss double"))


def evaluate_chunks(chunks: DataFrame, chunk_len: int, model: Forecaster, theta: np.ndarray, tau_c: int, tau_p: int) -> float:
    """Mean loss over all segments of chunks, which are cut where their loss is taken: none is written or sent."""
    shared = chunks.sparkSession.sparkContext.broadcast(theta)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total = 0, 0.0
        for batch in batches:
            for _, _, w in chunk_windows(batch, chunk_len, tau_c + tau_p):
                total += model.loss_only(shared.value, w[:, :tau_c], w[:, tau_c:]) * len(w)
                n += len(w)
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([total])], names=["n", "loss"])

    return _mean_loss(chunks.select("series_id", "t_first", "chunk_no", "values").mapInArrow(run, "n long, loss double"))


def _mean_loss(parts: DataFrame) -> float:
    row = parts.agg(F.sum("n").alias("n"), F.sum("loss").alias("loss")).first()
    return row["loss"] / row["n"] if row["n"] else float("nan")
