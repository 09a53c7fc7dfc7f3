"""What the operators share: reading tables, cutting lineage, components of a link graph."""

from __future__ import annotations

import ctypes
import gc
import tempfile
from collections.abc import Callable, Iterator
from functools import cache, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a small side above which a join is left to shuffle instead of being broadcast.
BROADCAST_ROWS = 200_000
#: A key with more than this part of the rows is hot; there are at most as many hot keys.
HOT_PART = 1000


#: Caches that the task before has left in this worker.
_LEFT: list[Callable] = []


@cache
def _trim() -> Callable | None:
    """The C library's function that gives freed memory back, if it has one."""
    return getattr(ctypes.CDLL(None), "malloc_trim", None)


def begin_task(keeps: Callable | None = None) -> None:
    """Drop what other operators' tasks have left in this worker; ``keeps`` is the cache of this one's."""
    other = [left for left in _LEFT if left is not keeps]
    for left in other:
        left.cache_clear()
    if other:
        gc.collect()  # what they held may refer to itself
    _LEFT[:] = [keeps] if keeps else []


def end_task() -> None:
    """Give freed memory back to the system."""
    if _trim():
        _trim()(0)


def lean(run: Callable[[Iterator], Iterator], keeps: Callable | None = None) -> Callable[[Iterator], Iterator]:
    """``run`` for workers that stay for the tasks of later stages: these find neither its caches nor memory that it has freed.

    ``keeps`` is a cached function whose values the next task of the same operator finds. A worker's memory is the executor's, beside that of the JVM.
    """

    def whole(batches: Iterator) -> Iterator:
        begin_task(keeps)
        try:
            yield from run(batches)
        finally:
            end_task()

    return whole


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only in local mode, where the session names none."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        if not sc.master.startswith("local"):
            raise ValueError("a cluster needs spark.checkpoint.dir, a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="predtopics-"))
    return sc.getCheckpointDir().rstrip("/")


def checkpoint(df: DataFrame) -> DataFrame:
    """Write the rows to the shared folder and forget how they were made."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def sized(small: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``small`` marked for broadcast if it has at most ``limit`` rows, else as it is (a shuffle join)."""
    return F.broadcast(small) if small.limit(limit + 1).count() <= limit else small


def discard(spark: SparkSession, path: str) -> None:
    """Remove a folder of the shared store, if it is there."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def join_unique(left: DataFrame, right: DataFrame, keys: list[str], how: str = "inner", limit: int = BROADCAST_ROWS) -> DataFrame:
    """``left`` joined with ``right``, which has one row a key, so that no key of ``left`` makes a hot task.

    A right side of at most ``limit`` rows is broadcast. Else the right rows of hot keys are (there are at most HOT_PART of them, as
    each has more than that part of the left rows), and all other keys are shuffled. Null keys match nothing. Both sides are read more than
    once, so they should be in the shared store.
    """
    if right.limit(limit + 1).count() <= limit:
        return left.join(F.broadcast(right), keys, how)
    counts = left.groupBy(*keys).count()
    hot = counts.where(F.col("count") > left.count() / HOT_PART).select(*keys)
    hot = hot.where(reduce(lambda a, b: a & b, [F.col(k).isNotNull() for k in keys]))
    of_hot = left.join(F.broadcast(hot), keys, "left_semi").join(F.broadcast(right.join(F.broadcast(hot), keys, "left_semi")), keys, how)
    return of_hot.unionByName(left.join(F.broadcast(hot), keys, "left_anti").join(right, keys, how))


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One step of alternating stars on (a > b) edges: link neighbours to the smallest one around."""
    if large:
        around = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionAll(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = checkpoint(around.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")))
        out = join_unique(around.where("v > u"), least, ["u"]).select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        least = checkpoint(edges.groupBy("a").agg(F.min("b").alias("m")))
        out = join_unique(edges, least, ["a"]).select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(least.select("a", F.col("m").alias("b")))
    return out.where("a <> b").distinct()


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(a, b) links of any order -> (node, root), root the smallest node reachable; only nodes that have links.

    Alternating large and small stars: the number of rounds grows with the logarithm of the longest
    path. Minima are taken by map-side combining aggregation and come to the links by a join that deals with hot nodes,
    so a node with very many links is no hot group; each step is written to the shared folder.
    """
    now = checkpoint(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct())
    state = None
    for _ in range(rounds):
        sums = now.agg(F.count("*"), F.sum(F.pmod(F.xxhash64("a", "b"), F.lit(1 << 40)))).first()
        if tuple(sums) == state or not sums[0]:
            break
        state = tuple(sums)
        now = checkpoint(_star(checkpoint(_star(now, True)), False))
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionAll(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
