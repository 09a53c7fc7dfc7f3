"""Approximate nearest neighbours by multiprobe p-stable hashing, reranked by exact cosine.

Vectors are scaled to length 1, where the largest cosine is the least Euclidean distance. A table hashes a vector by ``HASHES``
Gaussian projections, shifted and cut into cells of ``CELL``; their cell numbers are its bucket. A query visits, in each of
``TABLES`` tables, its own bucket and perturbed ones (a projection moved to the next cell on either side), in the order
of estimated success: the sum of squared distances to the cell walls that are crossed, least first. How many are visited is
fitted on a bounded sample (``SAMPLE`` rows, ``TRIALS`` queries) so that the sample's own neighbours are found with ``RECALL``;
all rows are indexed. Queries that find fewer than ``k`` rows so, though more exist, go on with every perturbation, and those that
still do are compared with all rows.

Buckets are dealt to shards by hash; a shard that holds more than ``BLOCK`` rows is split by vector, and its queries go
to every part. In a shard, rows are held in the order of their buckets (at most about a block) while queries stream past; a query is
multiplied with the rows in its buckets alone, and the best ``k`` of them leave the shard, so the number of rows that leave does not depend on the size of buckets.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import checkpoint, sized, table

TABLES, HASHES, CELL, BLOCK, SEED = 3, 8, 2.0, 32_768, 11
SAMPLE, TRIALS, RECALL = 4_000, 200, 0.97


@lru_cache(maxsize=4)
def moves(hashes: int) -> tuple[np.ndarray, np.ndarray]:
    """Every perturbation: moves (n, hashes) of -1, 0 or 1, and which of the 2*hashes walls (upper, lower) each crosses."""
    delta = np.array(list(itertools.product((0, 1, -1), repeat=hashes)), np.int64)
    return delta, np.concatenate([delta == 1, delta == -1], axis=1).astype(np.float64)


@dataclass
class Hashing:
    dim: int
    tables: int = TABLES
    hashes: int = HASHES
    cell: float = CELL
    seed: int = SEED
    probes: int = 64

    def _projections(self, t: int) -> tuple[np.ndarray, np.ndarray]:
        rng = np.random.default_rng([self.seed, t])
        return rng.normal(size=(self.dim, self.hashes)), rng.uniform(0, self.cell, self.hashes)

    def cells(self, unit: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
        """Cell numbers and the places within the cells."""
        a, b = self._projections(t)
        at = (unit @ a + b) / self.cell
        low = np.floor(at)
        return low.astype(np.int64), at - low

    def code(self, cells: np.ndarray) -> np.ndarray:
        return ((cells + 64) & 127) @ (np.int64(1) << (7 * np.arange(self.hashes, dtype=np.int64)))

    def probe(self, unit: np.ndarray, t: int) -> np.ndarray:
        """(queries, probes) buckets in estimated success order."""
        cells, place = self.cells(unit, t)
        delta, crossed = moves(self.hashes)
        cost = np.concatenate([(1 - place) ** 2, place**2], axis=1) @ crossed.T
        n = min(self.probes, len(delta))
        order = np.argsort(cost, axis=1, kind="stable")[:, :n]
        return self.code(cells[:, None, :] + delta[order])


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def cosines(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Cosine of one vector with rows, in doubles, the same for equal rows wherever they stand."""
    return (x * q).sum(axis=1) / (np.sqrt((q * q).sum()) * np.sqrt((x * x).sum(axis=1)))


def fitted(sample: np.ndarray, dim: int, k: int = 5, recall: float = RECALL, trials: int = TRIALS) -> Hashing:
    """Hashing with the fewest probes, of powers of two, that find the sample's own neighbours."""
    h = Hashing(dim)
    most = len(moves(h.hashes)[0])
    if len(sample) <= 2 * k:
        h.probes = most
        return h
    u = unit(sample)
    q = np.arange(min(trials, len(u)))
    s = u[q] @ u.T
    s[q, q] = -np.inf
    near = np.argsort(-s, axis=1)[:, :k]
    # the place of each neighbour's bucket in the order of probes, in the table where it is first
    first = np.full(near.shape, np.iinfo(np.int64).max)
    h.probes = most
    for t in range(h.tables):
        probed, codes = h.probe(u[q], t), h.code(h.cells(u, t)[0])
        for i in q:
            rank = {c: n for n, c in reversed(list(enumerate(probed[i].tolist())))}
            first[i] = np.minimum(first[i], [rank.get(int(codes[j]), most) for j in near[i]])
    h.probes = 1
    while h.probes < most and (first < h.probes).mean() < recall:
        h.probes *= 2
    h.probes = min(h.probes, most)
    return h


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def _index_rows(h: Hashing, shards: int):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not len(b):
                continue
            u = unit(_matrix(b.column(1), h.dim))
            for t in range(h.tables):
                code = h.code(h.cells(u, t)[0])
                shard = t * shards + _shard(code, t, shards)
                yield pa.RecordBatch.from_arrays([pa.array(shard), pa.array(code), b.column(0), b.column(1)], names=["shard", "bucket", "vec_id", "vec"])

    return run


def _shard(code: np.ndarray, t: int, shards: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (code.astype(np.uint64) + np.uint64(t + 1)) * np.uint64(0x9E3779B97F4A7C15)
    return ((x >> np.uint64(33)) % np.uint64(shards)).astype(np.int64)


def _query_rows(h: Hashing, shards: int):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, len(whole), 128):
                b = whole.slice(at, 128)
                u = unit(_matrix(b.column(1), h.dim))
                for t in range(h.tables):
                    probed = h.probe(u, t)
                    shard = _shard(probed, t, shards)
                    rows, places, lists = [], [], []
                    for i in range(len(b)):
                        order = np.argsort(shard[i], kind="stable")
                        cut = np.flatnonzero(np.diff(shard[i][order])) + 1
                        for part in np.split(order, cut):
                            rows.append(i)
                            places.append(int(shard[i][part[0]]) + t * shards)
                            lists.append(np.unique(probed[i][part]))
                    ends = np.cumsum([0, *map(len, lists)]).astype(np.int32)
                    buckets = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(lists)))
                    taken = b.take(pa.array(rows))
                    yield pa.RecordBatch.from_arrays([pa.array(places, pa.int64()), buckets, taken.column(0), taken.column(1)], names=["shard", "buckets", "vec_id", "vec"])

    return run


class Shard:
    """The rows of a shard in the order of their buckets, so that those of a bucket are a range."""

    def __init__(self, codes: np.ndarray, ids: np.ndarray, x: np.ndarray) -> None:
        order = np.argsort(codes, kind="stable")
        self.codes, self.ids, self.x = codes[order], ids[order], x[order]
        self.scale = 1 / np.sqrt((self.x * self.x).sum(axis=1))
        self.repeated = len(np.unique(ids)) < len(ids)

    def within(self, buckets: np.ndarray) -> np.ndarray:
        """Places of the rows in some distinct buckets."""
        low, high = np.searchsorted(self.codes, buckets, "left"), np.searchsorted(self.codes, buckets, "right")
        size = high - low
        return np.repeat(low - (np.cumsum(size) - size), size) + np.arange(size.sum())

    def best(self, q_id: int, q: np.ndarray, buckets: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and cosines of the best k rows in a query's buckets; no others are looked at."""
        at = self.within(buckets)
        at = at[self.ids[at] != q_id]
        if not len(at):
            return self.ids[:0], self.scale[:0]
        rough = (self.x[at] @ q) * self.scale[at] / np.sqrt((q * q).sum())
        each = rough
        if self.repeated:  # repeated ids count once
            names, owner = np.unique(self.ids[at], return_inverse=True)
            each = np.full(len(names), -np.inf)
            np.maximum.at(each, owner, rough)
        least = np.partition(each, -min(k, len(each)))[-min(k, len(each))]
        near = at[rough >= least - 1e-9]
        exact = cosines(q, self.x[near])
        order = np.lexsort((self.ids[near], -exact))
        order = order[np.sort(np.unique(self.ids[near][order], return_index=True)[1])][:k]
        return self.ids[near][order], exact[order]


def _search(dim: int, k: int):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows sorted by (shard, part, kind): a part's rows, then the queries that visit it."""
        here, codes, ids, vecs, ready = None, [], [], [], None
        for whole in batches:
            key = whole.column(0).to_numpy().astype(np.int64) * (1 << 20) + whole.column(1).to_numpy()
            kind = whole.column(2).to_numpy()
            cut = np.flatnonzero((np.diff(key) != 0) | (np.diff(kind) != 0)) + 1
            for a, e in itertools.pairwise([0, *cut.tolist(), len(key)]):
                if a == e:
                    continue
                b = whole.slice(a, e - a)
                if key[a] != here:
                    here, codes, ids, vecs, ready = key[a], [], [], [], None
                if kind[a] == 0:
                    codes.append(b.column(3).to_numpy())
                    ids.append(b.column(5).to_numpy())
                    vecs.append(_matrix(b.column(6), dim))
                    continue
                if not ids:
                    continue
                if ready is None:
                    ready = Shard(np.concatenate(codes), np.concatenate(ids), np.concatenate(vecs))
                    codes, vecs = [], []
                q_id, q, lists = b.column(5).to_numpy(), _matrix(b.column(6), dim), b.column(4)
                found = [ready.best(q_id[i], q[i], np.asarray(lists[i].values), k) for i in range(len(b))]
                names = np.repeat(q_id, [len(v) for v, _ in found])
                if len(names):
                    yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(np.concatenate([v for v, _ in found]), pa.int64()), pa.array(np.concatenate([s for _, s in found]), pa.float64())], names=["query_id", "vec_id", "score"])

    return run


def usable(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> tuple[DataFrame, int]:
    """(vec_id, vec) of the vectors that take part, and their dimension: the commonest length, of equals the larger."""
    size = F.size(vec_col)
    sizes = vectors.where(F.col(vec_col).isNotNull()).groupBy(size.alias("n")).count().where("n > 0").orderBy(F.desc("count"), F.desc("n")).first()
    dim = sizes["n"] if sizes else 1
    infinite = lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == float("inf"))
    fine = F.col(id_col).isNotNull() & (size == dim) & ~F.exists(vec_col, infinite) & F.exists(vec_col, lambda e: e != 0)
    return vectors.where(F.coalesce(fine, F.lit(False))).select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("vec")), dim


def nearest(vectors: DataFrame, is_query: Column, k: int = 5, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): of each row for which ``is_query`` holds (an expression over vec_id), its k nearest found.

    Ranks run from 1, nearest first by exact cosine, ties to the smaller id. Candidates are all rows but those of the query's own id. Vectors that
    are null, zero, of another length, or hold null or non-finite components take no part, nor do rows without id; repeated
    ids count once, with the best score. Empty frames give an empty result. Other columns are ignored.
    """
    rows, dim = usable(vectors, id_col, vec_col)
    spread = F.pmod(F.xxhash64("vec_id"), F.lit(1_000_000))
    n = rows.count()
    share = min(1_000_000, int(1_000_000 * 1.5 * SAMPLE / max(n, 1)) + 1)
    sample = rows.where(spread < share).orderBy(spread, "vec_id").limit(SAMPLE).collect()
    h = fitted(np.array([r["vec"] for r in sample], np.float64).reshape(-1, dim), dim, k)
    shards = max(1, -(-n // BLOCK))
    found = _visit(rows, rows.where(is_query), h, shards, k)
    exist = rows.select("vec_id").distinct().limit(k + 1).count() - 1  # others of a query, as far as k
    for wider in (replace(h, probes=len(moves(h.hashes)[0])), None):
        if wider == h:
            continue
        full = found.groupBy("query_id").count().where(F.col("count") >= exist).select(F.col("query_id").alias("vec_id"))
        lack = checkpoint(rows.where(is_query).join(full, "vec_id", "left_anti"))
        if exist < 1 or lack.isEmpty():
            break
        more = _visit(rows, lack, wider, shards, k) if wider else _compare(rows, lack, shards, k, dim)
        rest = found.join(lack.select(F.col("vec_id").alias("query_id")).distinct(), "query_id", "left_anti")
        found = rest.unionByName(more)
    return found


def _ranked(found: DataFrame, k: int) -> DataFrame:
    """The k best of what shards have found, written to the shared folder."""
    once = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return checkpoint(once.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score"))


def _visit(rows: DataFrame, queries: DataFrame, h: Hashing, shards: int, k: int) -> DataFrame:
    """What queries find in the buckets that they visit."""
    index = rows.mapInArrow(_index_rows(h, shards), "shard long, bucket long, vec_id long, vec array<double>")
    parts = checkpoint(index.groupBy("shard").count().select("shard", F.ceil(F.col("count") / F.lit(1.5 * BLOCK)).cast("int").alias("parts")))
    split = parts.where("parts > 1")
    part = F.when(F.col("parts").isNotNull(), F.pmod(F.xxhash64("vec_id"), F.col("parts")).cast("int")).otherwise(F.lit(0))
    none = F.lit(None).cast("array<bigint>")
    stored = index.join(sized(split), "shard", "left").select("shard", part.alias("part"), F.lit(0).alias("kind"), "bucket", none.alias("buckets"), "vec_id", "vec")
    asked = queries.mapInArrow(_query_rows(h, shards), "shard long, buckets array<bigint>, vec_id long, vec array<double>").join(sized(parts), "shard")
    asked = asked.select("shard", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(1).alias("kind"), F.lit(0).cast("long").alias("bucket"), "buckets", "vec_id", "vec")
    placed = stored.unionByName(asked).repartition("shard", "part").sortWithinPartitions("shard", "part", "kind")
    return _ranked(placed.mapInArrow(_search(h.dim, k), "query_id long, vec_id long, score double"), k)


def _compare(rows: DataFrame, queries: DataFrame, shards: int, k: int, dim: int) -> DataFrame:
    """What queries find among all rows, block by block."""
    zero = F.lit(0).cast("long")
    stored = rows.select(F.pmod(F.xxhash64("vec_id"), F.lit(shards)).alias("shard"), F.lit(0).alias("part"), F.lit(0).alias("kind"), zero.alias("bucket"), F.lit(None).cast("array<bigint>").alias("buckets"), "vec_id", "vec")
    every = F.explode(F.sequence(zero, F.lit(shards - 1).cast("long")))
    asked = queries.select(every.alias("shard"), F.lit(0).alias("part"), F.lit(1).alias("kind"), zero.alias("bucket"), F.array(zero).alias("buckets"), "vec_id", "vec")
    placed = stored.unionByName(asked).repartition("shard", "part").sortWithinPartitions("shard", "part", "kind")
    return _ranked(placed.mapInArrow(_search(dim, k), "query_id long, vec_id long, score double"), k)


def op7_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), F.col("vec_id") % 50 == 0)
