"""Joins, windows and set operations that plain Spark has no single call for, and thin ones for the rest."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..settle import small


def join(left: DataFrame, right: DataFrame, on, how: str = "inner", strategy: str | None = None) -> DataFrame:  # noqa: ANN001
    """strategy: broadcast (if the right side is small enough), merge, shuffle_hash or none."""
    if strategy == "broadcast":
        return left.join(small(right), on, how)
    return left.join(right.hint(strategy) if strategy else right, on, how)


def range_join(left: DataFrame, bands: DataFrame, value: str, lo: str, hi: str, width: float) -> DataFrame:
    """Rows with the bands that hold their value (lo <= value < hi): an equi-join on bins of a width, then the bounds."""
    bins = F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))
    dealt = bands.withColumn("__bin", F.explode(bins))
    return left.withColumn("__bin", F.floor(F.col(value) / width)).join(dealt, "__bin").where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("__bin")


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str, within: int, right_ts: str) -> DataFrame:
    """Rows of one key with right_ts in [ts, ts + within seconds]: buckets of that length meet, each left row in two."""
    bucket = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (within * 1_000_000))
    dealt = left.withColumn("__b", F.explode(F.array(bucket(ts), bucket(ts) + 1)))
    gap = F.unix_micros(F.col(right_ts).cast("timestamp")) - F.unix_micros(F.col(ts).cast("timestamp"))
    return dealt.join(right.withColumn("__b", bucket(right_ts)), [key, "__b"]).where((gap >= 0) & (gap <= within * 1_000_000)).drop("__b")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, payload: list[str], tolerance: int | None = None) -> DataFrame:
    """Each left row with the last right row of its key at or before its time: one union, one sort, no pairs."""
    both = left.select(key, ts, F.lit(1).alias("__side"), F.struct(*left.columns).alias("__l"), F.lit(None).cast(right.select(F.struct(ts, *payload)).schema[0].dataType).alias("__r")).unionByName(
        right.select(key, ts, F.lit(0).alias("__side"), F.lit(None).cast(left.select(F.struct(*left.columns)).schema[0].dataType).alias("__l"), F.struct(ts, *payload).alias("__r"))
    )
    w = W.partitionBy(key).orderBy(ts, "__side", "__r").rowsBetween(W.unboundedPreceding, W.currentRow)
    out = both.withColumn("__last", F.last("__r", ignorenulls=True).over(w)).where("__side = 1")
    near = F.lit(True) if tolerance is None else F.unix_micros(F.col(ts).cast("timestamp")) - F.unix_micros(F.col(f"__last.{ts}").cast("timestamp")) <= tolerance * 1_000_000
    return out.select("__l.*", *[F.when(near, F.col(f"__last.{c}")).alias(c) for c in payload])


def topk(df: DataFrame, keys: list[str], order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(W.partitionBy(*keys).orderBy(*order))).where(F.col("rank") <= k)


def multi_group(df: DataFrame, keys: list[str], how: str, *aggs: Column) -> DataFrame:
    """rollup or cube, with grouping_id as gid."""
    return getattr(df, how)(*keys).agg(F.grouping_id().alias("gid"), *aggs)


def sample_hash(df: DataFrame, key: str, frac: float, seed: int = 0) -> DataFrame:
    """A share of the rows that is the same on every run and in every partitioning."""
    return df.where(F.substring(F.md5(F.concat(F.col(key).cast("string"), F.lit(f"/{seed}")).cast("binary")), 1, 8) < f"{min(int(frac * 2**32), 2**32 - 1):08x}")


def setop(left: DataFrame, right: DataFrame, how: str) -> DataFrame:
    return {"union_distinct": lambda: left.union(right).distinct(), "union_all": lambda: left.unionAll(right), "intersect": lambda: left.intersect(right), "intersect_all": lambda: left.intersectAll(right), "except": lambda: left.subtract(right), "except_all": lambda: left.exceptAll(right)}[how]()
