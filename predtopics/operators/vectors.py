"""Vectors held against each other in blocks: rows are dealt into blocks of bounded size, and two blocks meet in one task as matrices.

Matrix products only choose; what is told is summed component by component in order, so equal vectors give equal values in any block.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..settle import settle, small

#: Rows of a block, about.
ROWS = 1024
#: By how much a product of matrices may differ from the sum in order, of vectors of length 1.
SLACK = 1e-9


def dealt(df: DataFrame, by: str, rows: int = ROWS) -> DataFrame:
    """(by, id, v) rows with part and block: blocks of about ``rows`` rows of one value of ``by`` (part), dealt by a hash of the id. Null values have none."""
    sizes = df.where(F.col(by).isNotNull()).groupBy(F.col(by).alias("part")).agg(F.ceil(F.count("*") / rows).alias("__k"))
    return df.join(small(sizes), F.col(by) == F.col("part")).withColumn("block", F.pmod(F.xxhash64("id"), F.col("__k"))).select("part", "block", "id", "v")


def meet(left: DataFrame, right: DataFrame, pairs: DataFrame, run: Callable, schema: str) -> DataFrame:
    """run(left table, right table) -> table of every pair of blocks. left, right: (part, block, ...) rows; pairs: (part, one, two)."""
    pairs = small(pairs)
    a = left.withColumnRenamed("block", "one").join(pairs, ["part", "one"]).groupBy("part", "one", "two")
    b = right.withColumnRenamed("block", "two").join(pairs, ["part", "two"])
    b = b.select(*[F.col(c).alias(c) for c in b.columns]).groupBy("part", "one", "two")  # own columns, as both sides may be one frame
    return a.cogroup(b).applyInArrow(run, schema)


def pairs_of(left: DataFrame, right: DataFrame, ordered: bool = True) -> DataFrame:
    """(part, one, two): blocks of a part; not ``ordered``: each pair once, by numbers."""
    a, b = left.select("part", F.col("block").alias("one")).distinct(), right.select("part", F.col("block").alias("two")).distinct()
    both = a.join(b, "part")
    return settle(both if ordered else both.where("one <= two"))


def matrix(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, vectors in double precision, and which rows have one whole; others are zero."""
    ids, v = t["id"].combine_chunks(), t["v"].to_pylist() if t["v"].null_count else None
    if v is None:
        flat = t["v"].combine_chunks().flatten()
        if not flat.null_count:
            return ids, flat.to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(t), -1), np.ones(len(t), bool)
        v = t["v"].to_pylist()
    whole = np.array([x is not None and None not in x for x in v], bool)
    width = max((len(x) for x, w in zip(v, whole) if w), default=0)
    return ids, np.array([x if w else [0.0] * width for x, w in zip(v, whole)], np.float64).reshape(len(t), width), whole


def summed(x: np.ndarray, y: np.ndarray, difference: bool = False) -> np.ndarray:
    """Products, or squares of differences, of paired rows, summed in order."""
    out = np.zeros(len(x))
    for k in range(x.shape[1]):
        out += (x[:, k] - y[:, k]) ** 2 if difference else x[:, k] * y[:, k]
    return out


def _cosines(left: pa.Table, right: pa.Table) -> pa.Table:
    (ids, x, whole), (others, y, too) = matrix(left), matrix(right)
    ids, others = ids.to_numpy(), others.to_numpy()
    with np.errstate(invalid="ignore", divide="ignore"):
        cos = (x @ y.T) / (np.sqrt(summed(x, x))[:, None] * np.sqrt(summed(y, y))[None, :]) if whole.any() and too.any() else np.zeros((len(ids), len(others)))
    none = ~(whole[:, None] & too[None, :])
    if left["one"][0] == left["two"][0]:
        at = np.nonzero(ids[:, None] < others[None, :])
        a, b, cos, none = ids[at[0]], others[at[1]], cos[at], none[at]
    else:
        n = len(others)
        p, q = np.repeat(ids, n), np.tile(others, len(ids))
        a, b, cos, none = np.minimum(p, q), np.maximum(p, q), cos.ravel(), none.ravel()
    return pa.table({"a": a, "b": b, "cos": pa.array(np.round(cos, 5) + 0.0, mask=none if none.any() else None, from_pandas=False)})


def pair_cosines(df: DataFrame, by: str) -> DataFrame:
    """(a, b, cos): cosines, to five places, of all pairs a < b of (by, id, v) rows with one value of ``by``; ids are whole numbers. Without a whole vector a cosine is null, with a zero one NaN."""
    rows = settle(dealt(df, by))
    return meet(rows, rows, pairs_of(rows, rows, ordered=False), _cosines, "a long, b long, cos double")


def _best(k: int):  # noqa: ANN202
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        (ids, x, whole), (others, y, too) = matrix(left), matrix(right)
        ids, others = ids.to_numpy(), others.to_numpy()
        nx, ny = np.sqrt(summed(x, x)), np.sqrt(summed(y, y))
        some = [[], [], [], []]
        for at in range(0, len(ids), 256):
            end = min(at + 256, len(ids))
            with np.errstate(invalid="ignore", divide="ignore"):
                near = (x[at:end] @ y.T) / (nx[at:end, None] * ny[None, :]) if x.shape[1] == y.shape[1] else np.zeros((end - at, len(others)))
            near[np.isnan(near)] = np.inf  # as sorting has it
            near[~(whole[at:end, None] & too[None, :])] = -2.0
            same = ids[at:end, None] == others[None, :]
            near[same] = -np.inf
            least = np.partition(near, len(others) - k, axis=1)[:, -k] if len(others) > k else np.full(end - at, -3.0)
            r, c = np.nonzero((near >= (least - SLACK)[:, None]) & ~same)
            with np.errstate(invalid="ignore", divide="ignore"):
                cos = summed(x[at + r], y[c]) / (nx[at + r] * ny[c]) if x.shape[1] == y.shape[1] else np.zeros(len(r))
            none = ~(whole[at + r] & too[c])
            order = np.lexsort((others[c], -np.where(none, -2.0, np.where(np.isnan(cos), np.inf, cos)), r))
            r, c, cos, none = r[order], c[order], cos[order], none[order]
            held = np.arange(len(r)) - np.searchsorted(r, r) < k
            for to, what in zip(some, (ids[at + r], others[c], cos, none)):
                to.append(what[held])
        a, b, cos, none = (np.concatenate(s) for s in some)
        return pa.table({"label": pa.array([left["part"][0].as_py()] * len(a), left.schema.field("part").type), "a": a, "b": b, "cos": pa.array(cos, mask=none, from_pandas=False)})

    return run


def nearest(df: DataFrame, by: str, k: int) -> DataFrame:
    """(label, a, b, cos): of each (by, id, v) row the k of largest cosine, ties to the smaller id, in each block of other rows with its value of ``by``; the k nearest of all are among them."""
    rows = settle(dealt(df, by))
    return meet(rows, rows, pairs_of(rows, rows), _best(k), f"label {df.schema[by].dataType.simpleString()}, a long, b long, cos double")


def _within(radius: float):  # noqa: ANN202
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        (ids, x, whole), (others, y, too) = matrix(left), matrix(right)
        some = [], [], []
        if whole.any() and too.any():
            x2, y2 = summed(x, x), summed(y, y)
            slack = SLACK * (1 + float(x2.max()) + float(y2.max()))
            for at in range(0, len(x), 512):
                part = slice(at, at + 512)
                far = x2[part, None] + y2[None, :] - 2 * (x[part] @ y.T)
                r, c = np.nonzero((far <= radius * radius + slack) & whole[part, None] & too[None, :])
                for lo in range(0, len(r), 1 << 18):
                    p, q = at + r[lo : lo + (1 << 18)], c[lo : lo + (1 << 18)]
                    d = np.sqrt(summed(x[p], y[q], True))
                    hit = d <= radius
                    for to, what in zip(some, (p[hit], q[hit], d[hit])):
                        to.append(what)
        p, q, d = (np.concatenate(s) if s else np.zeros(0, t) for s, t in zip(some, (int, int, float)))
        return pa.table({"id1": ids.take(pa.array(p)), "id2": others.take(pa.array(q)), "d": d})

    return run


def within(left: DataFrame, right: DataFrame, radius: float, pivots: int, rows: int = 2 * ROWS) -> DataFrame:
    """(id1, id2, d) with distance d up to radius, of (id, v, far) rows, far the distances to ``pivots`` common points.

    Blocks are ranges of the distance to the first point; larger ones, as of many equal vectors, are dealt by a hash of the id. Two blocks
    meet if by the triangle inequality they can hold a pair: their ranges of distances to every point are within radius of each other.
    """
    def ranged(df: DataFrame) -> DataFrame:
        first, n = F.element_at("far", 1), df.count()
        shares = [k / max(1, n // rows) for k in range(1, max(1, n // rows))]
        cuts = sorted(set(df.approxQuantile("__f", shares, 0.01))) if shares else []
        df = df.withColumn("__cell", F.size(F.filter(F.array(*[F.lit(c) for c in cuts]).cast("array<double>"), lambda c: c <= first)) if cuts else F.lit(0))
        sizes = df.groupBy("__cell").agg(F.ceil(F.count("*") / (2 * rows)).alias("__k"))
        df = df.join(small(sizes), "__cell").withColumn("block", F.col("__cell").cast("long") * (1 << 32) + F.pmod(F.xxhash64("id"), F.col("__k")))
        return settle(df.select(F.lit(0).alias("part"), "block", "id", "v", "far"))

    sides = [ranged(df.where(F.col("v").isNotNull()).withColumn("__f", F.element_at("far", 1))) for df in (left, right)]
    bounds = [df.groupBy("block").agg(*[f(F.element_at("far", k + 1)).alias(f"{n}{k}") for k in range(pivots) for n, f in (("lo", F.min), ("hi", F.max))]) for df in sides]
    one, two = bounds[0].withColumnRenamed("block", "one"), bounds[1].select(F.col("block").alias("two"), *[F.col(c).alias("r" + c) for c in bounds[1].columns if c != "block"])
    near = F.lit(True)
    for k in range(pivots):
        near &= (F.col(f"lo{k}") <= F.col(f"rhi{k}") + radius + SLACK) & (F.col(f"rlo{k}") <= F.col(f"hi{k}") + radius + SLACK)
    pairs = settle(one.crossJoin(two).where(near).select(F.lit(0).alias("part"), "one", "two"))
    kinds = [df.schema["id"].dataType.simpleString() for df in sides]
    return meet(sides[0].drop("far"), sides[1].drop("far"), pairs, _within(radius), f"id1 {kinds[0]}, id2 {kinds[1]}, d double")
