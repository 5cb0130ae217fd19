"""What several operators share: cutting lineage, hot-key lookups, connected components."""

from __future__ import annotations

import ctypes
import re
import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A key is hot when it holds at least one in HOT_SHARE of all rows; so there are HOT_SHARE hot keys at most.
HOT_SHARE = 4096
#: Rows of a hot key are spread over so many salts.
SALTS = 64
#: Edges of a graph, at 16 bytes each, whose components the driver finds; larger graphs are contracted by jobs.
DRIVER_EDGES = 200_000
#: Rows and bytes of an Arrow batch at most.
BATCH_ROWS = 500
BATCH_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut lineage in the shared folder that the session names."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder as a URI that Spark's readers and writers take.

    It is spark.checkpoint.dir. Where that is unset, a local master, whose tasks share this machine's disk, gets a folder of its own; a cluster gets an error.
    """
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not re.match(r"local($|\[)", context.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp("-checkpoints"))
    return context.getCheckpointDir()


def collect_garbage(spark: SparkSession) -> None:
    """Have the driver's JVM collect its garbage: only then does Spark delete the shuffle and checkpoint files of plans that are gone."""
    spark.sparkContext._jvm.System.gc()


def small_batches(spark: SparkSession) -> None:
    """Keep Arrow batches small where the session would make them large: whole texts travel in them, and an executor holds several at once."""
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)):
        now = spark.conf.get(key, None)
        if spark.conf.isModifiable(key) and now is not None and not 0 < _number(now) <= most:
            spark.conf.set(key, str(most))


def frugal(run: Callable) -> Callable:
    """run over Arrow batches, and hand freed memory back to the machine when a task ends: Python workers live on between tasks."""

    def wrapped(batches: Iterator) -> Iterator:
        try:
            yield from run(batches)
        finally:
            release_memory()

    return wrapped


def release_memory() -> None:
    pa.default_memory_pool().release_unused()
    libc = ctypes.CDLL(None)
    if hasattr(libc, "malloc_trim"):
        libc.malloc_trim(0)


def _number(text: str) -> int:
    """A setting that is a number, or a size such as 256MB."""
    digits = re.match(r"-?\d+", text.strip())
    unit = {"k": 10, "m": 20, "g": 30, "t": 40}.get(text.strip().lower()[len(digits[0]) :][:1], 0) if digits else 0
    return int(digits[0]) << unit if digits else -1


def hot_keys(rows: DataFrame, key: str, total: int) -> DataFrame:
    """The keys (_hot) of at least total / HOT_SHARE and more than 1000 of the rows: HOT_SHARE of them at most, by partial counts."""
    return rows.groupBy(key).agg(F.count(F.lit(1)).alias("_n")).filter((F.col("_n") * HOT_SHARE >= F.lit(total)) & (F.col("_n") > 1000)).select(F.col(key).alias("_hot"))


def salted_join(rows: DataFrame, groups: DataFrame, key: str, hot: DataFrame, salt_by: str, how: str = "left") -> DataFrame:
    """Join many rows to one row per key; rows of the hot keys, and those without a key, are spread over SALTS salts.

    hot (_hot) has HOT_SHARE rows at most, which bounds its broadcast; the group row of a hot key is repeated once per salt.
    """
    hot = F.broadcast(hot.filter("_hot is not null"))
    salt = F.pmod(F.xxhash64(salt_by), F.lit(SALTS)).cast("int")
    salted = rows.join(hot, rows[key] == hot["_hot"], "left").withColumn("_salt", F.when(F.col("_hot").isNotNull() | F.col(key).isNull(), salt).otherwise(F.lit(0))).drop("_hot")
    every = F.when(F.col("_hot").isNotNull(), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
    copies = groups.join(hot, groups[key] == hot["_hot"], "left").withColumn("_salt", F.explode(every)).drop("_hot")
    return salted.join(copies, [key, "_salt"], how).drop("_salt")


def hot_safe_lookup(rows: DataFrame, groups: DataFrame, key: str, members: str, total: int, salt_by: str = "doc_id") -> DataFrame:
    """Left join of many rows to one row per key, where one key, or none at all, may hold a large share of all rows.

    groups has one row per key; members counts the rows of the key. Keys with at least total / HOT_SHARE rows are salted.
    """
    hot = groups.filter((F.col(members) * HOT_SHARE >= F.lit(total)) & (F.col(members) > 1000)).select(F.col(key).alias("_hot"))
    return salted_join(rows, groups, key, hot, salt_by)


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node of the undirected edges (a, b); root is the smallest node reachable.

    Contraction: each node takes the smallest id among itself and its neighbours, parents are followed, doubling the way each time, to the node that is its
    own parent, edges are renamed and those inside a component vanish. Such a node has another below it, so the nodes left at least halve each round,
    also on a chain; each round cuts its lineage.
    Null ends and loops are left out. Graphs, also contracted ones, of DRIVER_EDGES at most come to the driver: a round takes some ten stages, whose tasks, files and
    events would outweigh so small a graph.
    """
    live = checkpointed(edges.select("a", "b").filter("a is not null and b is not null and a != b").distinct())
    roots = None
    while total := live.count():
        if total <= DRIVER_EDGES:
            ends = live.toArrow()
            table = pa.table(_smallest_reachable(ends["a"].to_numpy(), ends["b"].to_numpy()), names=["node", "root"])
            found = edges.sparkSession.createDataFrame(table)
            return found if roots is None else _followed(roots, found.toDF("root", "up"))
        ends = live.union(live.select("b", "a")).toDF("node", "other")
        parent = checkpointed(ends.groupBy("node").agg(F.least(F.col("node"), F.min("other")).alias("up")))
        moving = True
        while moving:
            above = parent.select(F.col("node").alias("up"), F.col("up").alias("top"))
            stepped = salted_join(parent, above, "up", hot_keys(parent, "up", total), "node", "inner").select("node", F.col("top").alias("up"), (F.col("top") != F.col("up")).alias("moved"))
            stepped = checkpointed(stepped)
            moving = not stepped.filter("moved").isEmpty()
            parent = stepped.select("node", "up")
        if roots is None:
            roots = parent.select("node", F.col("up").alias("root"))
        else:
            roots = _followed(roots, parent.select(F.col("node").alias("root"), "up"))
        left = parent.select(F.col("node").alias("a"), F.col("up").alias("ua"))
        right = parent.select(F.col("node").alias("b"), F.col("up").alias("ub"))
        named = salted_join(live, left, "a", hot_keys(live, "a", total), "b")
        named = salted_join(named, right, "b", hot_keys(live, "b", total), "a")
        live = checkpointed(named.filter("ua != ub").select(F.least("ua", "ub").alias("a"), F.greatest("ua", "ub").alias("b")).distinct())
    if roots is None:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root")).limit(0)
    return roots


def _followed(roots: DataFrame, step: DataFrame) -> DataFrame:
    """roots (node, root) after the step (root, up) that some of the roots take."""
    return checkpointed(salted_join(roots, step, "root", hot_keys(roots, "root", roots.count()), "node").select("node", F.coalesce("up", "root").alias("root")))


def _smallest_reachable(a: np.ndarray, b: np.ndarray) -> list[np.ndarray]:
    """The nodes of the edges, and the smallest node that each reaches."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    a, b = at[: len(a)], at[len(a) :]
    up = np.arange(len(nodes))
    while len(a):
        least = np.minimum(up[a], up[b])
        np.minimum.at(up, up[a], least)
        np.minimum.at(up, up[b], least)
        while not np.array_equal(up, top := up[up]):
            up = top
        apart = up[a] != up[b]
        a, b = a[apart], b[apart]
    return [nodes, nodes[up]]
