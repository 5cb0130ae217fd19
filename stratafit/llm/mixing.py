"""Mixing sources to target weights by entropy balancing."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stratafit.llm.common import checkpointed

WORD = r"[^\x20\x09-\x0D]+"
#: Rows that one task rounds together, about.
BLOCK_ROWS = 4_000
#: Rows alike in id, source and text that go to one block together at most.
ALIKE_ROWS = 1_000
WEIGHTS = (5.0, 2.0, 1.0)
CAP = 3.0


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text.cast("string"), F.lit(WORD)), F.lit(0)).cast("long")


def capped_targets(sizes: dict[object, int], weights: dict[object, float], cap: float = CAP) -> dict[object, float]:
    """Shares of the total by weight, where none passes cap times its own size; what a capped one leaves is reshared by weight among the rest."""
    total = float(sum(sizes.values()))
    target: dict[object, float] = {}
    left, open_ = total, [k for k in sizes]
    while open_:
        w = sum(weights[k] for k in open_)
        over = [k for k in open_ if left * weights[k] / w > cap * sizes[k]]
        if not over:
            target.update({k: left * weights[k] / w for k in open_})
            break
        for k in over:
            target[k] = cap * sizes[k]
        left -= sum(target[k] for k in over)
        open_ = [k for k in open_ if k not in target]
    return target


def balance(cells: DataFrame, constraints: Sequence[str], targets: dict[tuple[int, object], float], tokens: str = "tokens", iterations: int = 50, tolerance: float = 1e-9) -> dict[tuple[int, object], float]:
    """The multipliers of the entropy-balancing dual.

    Rates r minimise sum(tokens * (r log r - r + 1)) under: for each column of constraints and each of its values that has a target, the rates
    times tokens of the rows with that value sum to the target. So r = exp(sum of the row's multipliers). Each Newton step is one Spark job: the
    current masses of all pairs of constraint values, which are the gradient and the Hessian of the convex dual; steps are halved until the dual falls.
    Rows are pre-aggregated by their constraint values. The driver holds a vector and matrix of the number of targets, not of documents.
    Values of a null are kept apart as null. Targets of 0, or of values without tokens, get a multiplier of minus infinity.
    """
    grouped = checkpointed(cells.groupBy(*constraints).agg(F.sum(tokens).alias("_mass")))
    names = [k for k, t in targets.items() if t > 0]
    at = {k: i for i, k in enumerate(names)}
    spark: SparkSession = cells.sparkSession
    multipliers = np.zeros(len(names))
    goal = np.array([targets[k] for k in names])
    scale = max(1.0, goal.sum())

    def evaluate(values: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        dead = [k for k, t in targets.items() if t <= 0]
        lists = []
        rate: Column = F.lit(0.0)
        state = grouped
        for c, column in enumerate(constraints):
            rows = [(k[1], float(values[at[k]]), at[k]) for k in names if k[0] == c] + [(k[1], float("-inf"), -1) for k in dead if k[0] == c]
            small = spark.createDataFrame(rows, f"_v{c} {dict(grouped.dtypes)[column]}, _m{c} double, _i{c} int")
            state = state.join(F.broadcast(small), F.col(column).eqNullSafe(F.col(f"_v{c}")), "left")
            rate = rate + F.coalesce(F.col(f"_m{c}"), F.lit(0.0))
            lists.append(F.coalesce(F.col(f"_i{c}"), F.lit(-1)))
        masses = state.select(F.array(*lists).alias("_k"), (F.col("_mass") * F.exp(rate)).alias("_w")).groupBy("_k").agg(F.sum("_w").alias("_w")).collect()
        gradient, hessian, dual = -goal.copy(), np.zeros((len(names), len(names))), -float(goal @ values)
        for r in sorted(masses, key=lambda r: list(r["_k"])):
            own = [i for i in r["_k"] if i >= 0]
            dual += r["_w"]
            for i in own:
                gradient[i] += r["_w"]
                for j in own:
                    hessian[i, j] += r["_w"]
        return dual, gradient, hessian

    dual, gradient, hessian = evaluate(multipliers)
    for _ in range(iterations):
        if not len(names) or np.abs(gradient).max() <= tolerance * scale:
            break
        step = np.linalg.lstsq(hessian, gradient, rcond=None)[0]
        size = 1.0
        while True:
            trial = multipliers - size * step
            if np.abs(trial).max() < 700:
                new = evaluate(trial)
                if np.isfinite(new[0]) and new[0] <= dual - 1e-4 * size * float(gradient @ step) + 1e-12 * scale:
                    break
            size /= 2
            if size < 1e-8:
                return {k: float(multipliers[i]) for k, i in at.items()} | {k: float("-inf") for k, t in targets.items() if t <= 0}
        multipliers, (dual, gradient, hessian) = trial, new
    return {k: float(multipliers[i]) for k, i in at.items()} | {k: float("-inf") for k, t in targets.items() if t <= 0}


def _rounded(table: pa.Table, cap: float) -> pa.Table:
    """Copies of one block: each rate rounded with what longer documents left over or owe, largest documents first, 0 to cap times. Each row stands for as many as alike says."""
    table = table.sort_by([("size", "descending"), ("doc_id", "ascending"), ("text_hash", "ascending")])
    table = table.take(np.repeat(np.arange(len(table)), table["alike"].to_numpy())).drop_columns(["alike"])
    most = int(cap)
    copies, debt = [], 0.0
    for rate, n in zip(table["rate"].to_pylist(), table["size"].to_pylist(), strict=True):
        debt += rate * n
        c = min(most, max(0, int(debt / n + 0.5))) if n else min(most, int(rate + 0.5))
        copies.append(c)
        debt -= c * n
    return table.append_column("copies", pa.array(copies, pa.int64()))


def mix_sources(docs: DataFrame, weights: Sequence[float] = WEIGHTS, cap: float = CAP, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """doc_id, source, size, text_hash, source_size, target, rate, copies, taken; one row per row of docs (doc_id, text, source).

    size counts the words of the text, a null has none. Sources in code point order, null last, weigh the given weights, repeating; their targets
    share all words, at most cap times their own. The rates come from balance(); copies are the rates, rounded to at most
    cap, so taken = copies * size passes cap * size nowhere. Within blocks of a source, by a hash of id and text, rounding errors are carried on from long to short documents, so a
    source's taken words miss its target by about its shortest documents, unless one document is most of a source. An empty table gives no rows.
    Rows that repeat a doc_id, or whose id is null, are mixed row by row; rows alike in id and text are counted first and spread over blocks, ALIKE_ROWS together, so no
    group of copies is one task's. Other columns, whatever their names, are not read.
    """
    sized = checkpointed(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size"), F.xxhash64(F.col("text").cast("string")).alias("text_hash")))
    stats = sized.groupBy("source").agg(F.sum("size").alias("s"), F.count(F.lit(1)).alias("n")).collect()
    order = sorted(stats, key=lambda r: (r["source"] is None, (r["source"] or "").encode()))
    sizes = {r["source"]: int(r["s"]) for r in order}
    targets = capped_targets(sizes, {r["source"]: weights[i % len(weights)] for i, r in enumerate(order)}, cap)
    found = balance(sized.withColumn("tokens", F.col("size")), ["source"], {(0, k): t for k, t in targets.items()})
    plan = [(k, sizes[k], float(targets[k]), min(cap, float(np.exp(found[(0, k)]))) if targets[k] > 0 else 0.0, max(1, -(-int(r["n"]) // block_rows))) for r in order for k in [r["source"]]]
    plan = docs.sparkSession.createDataFrame(plan, "_source string, source_size long, target double, rate double, blocks int")
    counted = sized.groupBy("doc_id", "source", "size", "text_hash").agg(F.count(F.lit(1)).alias("n"))
    spread = counted.withColumn("part", F.explode(F.sequence(F.lit(0), F.floor((F.col("n") - 1) / ALIKE_ROWS).cast("int")))).withColumn("alike", F.least(F.lit(ALIKE_ROWS), F.col("n") - F.col("part") * ALIKE_ROWS)).drop("n")
    block = F.pmod(F.xxhash64("doc_id", "text_hash", "part"), F.col("blocks")).cast("int")
    rated = spread.join(F.broadcast(plan), F.col("source").eqNullSafe(F.col("_source"))).withColumn("block", block).drop("_source", "blocks", "part")

    def run(table: pa.Table) -> pa.Table:
        return _rounded(table, cap).drop_columns(["block"])

    kept = "doc_id long, source string, size long, text_hash long, source_size long, target double, rate double, copies long"
    return rated.groupBy("source", "block").applyInArrow(run, kept).withColumn("taken", F.col("copies") * F.col("size"))


def repeat_rows(docs: DataFrame, mixed: DataFrame) -> DataFrame:
    """docs with each row repeated as often as its copies say, 0 times included.

    Rows are met by doc_id, source and a hash of the text, nulls included. Those alike in all three are numbered, in the order of a hash of their other columns, and
    take the copies of mixed in ascending order, each row one of them; what they meet is how many rows take each number of copies, cap + 1 counts at most.
    """

    def keys(frame: DataFrame, text_hash: Column) -> list[Column]:
        doc_id, source = frame["doc_id"].cast("long"), frame["source"].cast("string")
        return [F.coalesce(doc_id, F.lit(0)).alias("_id"), doc_id.isNull().alias("_no_id"), F.coalesce(source, F.lit("")).alias("_source"), source.isNull().alias("_no_source"), text_hash.alias("_text")]

    names = ["_id", "_no_id", "_source", "_no_source", "_text"]
    counts = mixed.select(*keys(mixed, mixed["text_hash"]), "copies").groupBy(*names, "copies").agg(F.count(F.lit(1)).alias("_rows"))
    steps = counts.groupBy(*names).agg(F.sort_array(F.collect_list(F.struct("copies", "_rows"))).alias("_steps"))
    hashable = [docs[f.name] for f in docs.schema if f.name != "text" and not any(kind in f.dataType.simpleString() for kind in ("map<", "variant"))]
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("_row"), *keys(docs, F.xxhash64(docs["text"].cast("string"))), F.xxhash64(F.lit(0), *hashable).alias("_rest"))
    numbered = rows.join(steps, names).withColumn("_number", F.row_number().over(Window.partitionBy(*names).orderBy("_rest")).cast("long"))
    passed = F.aggregate("_steps", F.struct(F.col("_number").alias("left"), F.lit(0).cast("long").alias("own")), lambda a, s: F.when(a["left"] > 0, F.struct((a["left"] - s["_rows"]).alias("left"), s["copies"].alias("own"))).otherwise(a))
    own = passed["own"].cast("int")
    return numbered.select("_row", own.alias("_n")).filter("_n > 0").select("_row", F.explode(F.sequence(F.lit(1), F.col("_n"))).alias("_copy")).select("_row.*")
