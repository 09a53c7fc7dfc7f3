"""Estimates for volumes at which exact neighbourhoods are too large."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..settle import settle
from .similarity import share_scores
from .vectors import meet, pairs_of

#: Threshold of a sketch that retains every hash.
WHOLE = (1 << 63) - 1


def retained(sketch: bytes) -> tuple[np.ndarray, int]:
    """Hashes that a compact theta sketch retains, and its threshold, of 63 bits each; ordered differences packed in bits, or plain."""
    longs, packed, held = sketch[0] & 63, sketch[1] == 4, len(sketch)
    if packed:
        at = 16 if longs > 1 else 8
        theta = int.from_bytes(sketch[8:16], "little") if longs > 1 else WHOLE
        width, n = sketch[3], int.from_bytes(sketch[at : at + sketch[4]], "little")
        raw = np.frombuffer(sketch[at + sketch[4] :] + bytes(9), np.uint8)
        bit = np.arange(n, dtype=np.int64) * width
        byte, shift = bit >> 3, (bit & 7).astype(np.uint64)
        long = np.zeros(n, np.uint64)
        for k in range(8):
            long = long << np.uint64(8) | raw[byte + k]
        long = long << shift | raw[byte + 8].astype(np.uint64) >> (np.uint64(8) - shift)
        return np.cumsum(long >> np.uint64(64 - width)).astype(np.int64), theta
    if longs == 1:
        return np.frombuffer(sketch, "<i8", 1, 8) if held > 8 and not sketch[5] & 4 else np.zeros(0, np.int64), WHOLE
    n = int.from_bytes(sketch[8:12], "little")
    return np.frombuffer(sketch, "<i8", n, 8 * longs), int.from_bytes(sketch[16:24], "little") if longs > 2 else WHOLE


def _intersections(left: pa.Table, right: pa.Table) -> pa.Table:
    """Estimates of a block's sketches with another's. A hash that two sketches retain is below both thresholds, so what both retain is their intersection."""
    sides, same = [], left["one"][0] == left["two"][0]
    for t in (left,) if same else (left, right):
        held = [retained(k) for k in t["k"].to_pylist()]
        sides.append((t["p"].combine_chunks(), t["n"].to_numpy(), np.array([th for _, th in held], np.int64), np.concatenate([h for h, _ in held]), np.repeat(np.arange(len(held)), [len(h) for h, _ in held])))
    (p, n, theta, h, row), (q, m, theta2, h2, row2) = sides[0], sides[-1]
    known = np.unique(h) if same else np.intersect1d(h, h2)
    places = []
    for hashes, rows in ((h, row), (h2, row2)):
        at = np.minimum(np.searchsorted(known, hashes), max(len(known) - 1, 0))
        hit = known[at] == hashes if len(known) else np.zeros(len(hashes), bool)
        order = np.argsort(at[hit], kind="stable")
        places.append((at[hit][order], rows[hit][order]))
    met = np.zeros((len(p), len(q)), np.float32)  # counts, exact below 2 ** 24
    for lo in range(0, len(known), 4096):
        parts = []
        for (at, rows), size in zip(places, (len(p), len(q))):
            a, b = np.searchsorted(at, (lo, lo + 4096))
            part = np.zeros((size, 4096), np.float32)
            part[rows[a:b], at[a:b] - lo] = 1
            parts.append(part)
        met += parts[0] @ parts[1].T
    names = [x.to_pylist() for x in (p, q)]
    rank = {x: k for k, x in enumerate(sorted({*names[0], *names[1]}))}
    first, second = (np.array([rank[x] for x in side], np.int64) for side in names)
    i, j = np.nonzero((met > 0) & (first[:, None] < second[None, :]) if same else met > 0)
    least = np.minimum(theta[i], theta2[j])
    n12 = np.floor(np.where(least == WHOLE, met[i, j], met[i, j] / (least / WHOLE)) + 0.5).astype(np.int64)
    turn = first[i] > second[j]
    n1, n2 = np.where(turn, m[j], n[i]), np.where(turn, n[i], m[j])
    order = pa.array(sorted(rank), p.type)
    ends = [order.take(pa.array(np.where(turn, a, b))) for a, b in ((second[j], first[i]), (first[i], second[j]))]
    return pa.table({"p1": ends[0], "p2": ends[1], "n1": n1, "n2": n2, "n12": n12, "share": (n12 * n12) / (n1 * n2)})


def share_scores_theta(nbr: DataFrame, lg_k: int = 14, rows: int = 1024) -> DataFrame:
    """(p1, p2, n1, n2, n12, share) estimated from one theta sketch a predicate; sketches cross the shuffle, links do not.

    Sketches meet in blocks of about ``rows``, where a product of matrices counts what each two retain; the estimates are the sketches' own.
    """
    sk = settle(nbr.where("p is not null").groupBy("p").agg(F.theta_sketch_agg("concept", lg_k).alias("k")))
    k = max(1, -(-sk.count() // rows))
    sk = sk.select(F.lit(0).alias("part"), F.pmod(F.xxhash64("p"), F.lit(k)).alias("block"), F.col("p").cast("string").alias("p"), "k", F.theta_sketch_estimate("k").alias("n"))
    return meet(sk, sk, pairs_of(sk, sk, ordered=False), _intersections, "p1 string, p2 string, n1 long, n2 long, n12 long, share double")


def share_scores_lsh(nbr: DataFrame, bands: int = 64, rows: int = 2) -> DataFrame:
    """Exact shares of the pairs that agree in one band of min-hashes at least: candidates first, then the exact join on them."""
    seeds = F.array(*[F.lit(i) for i in range(bands * rows)])
    mins = nbr.select("p", F.posexplode(F.transform(seeds, lambda s: F.xxhash64(F.col("concept"), s))).alias("i", "h")).groupBy("p", "i").agg(F.min("h").alias("h"))
    keys = mins.groupBy("p", F.floor(F.col("i") / rows).alias("band")).agg(F.xxhash64(F.array_sort(F.collect_list(F.struct("i", "h"))).cast("string")).alias("key"))
    left, right = keys.select(F.col("p").alias("p1"), "band", "key"), keys.select(F.col("p").alias("p2"), "band", "key")
    candidates = left.join(right, ["band", "key"]).where("p1 < p2").select("p1", "p2").distinct()
    sizes = nbr.groupBy("p").agg(F.count("*").alias("n"))
    met = candidates.join(nbr.select(F.col("p").alias("p1"), "concept"), "p1").join(nbr.select(F.col("p").alias("p2"), "concept"), ["p2", "concept"]).groupBy("p1", "p2").agg(F.count("*").alias("n12"))
    out = met.join(sizes.select(F.col("p").alias("p1"), F.col("n").alias("n1")), "p1").join(sizes.select(F.col("p").alias("p2"), F.col("n").alias("n2")), "p2")
    return out.select("p1", "p2", "n1", "n2", "n12", (F.col("n12") * F.col("n12") / (F.col("n1") * F.col("n2"))).alias("share"))


def share_error(nbr: DataFrame, estimate: DataFrame) -> DataFrame:
    """(pairs, mean_error, worst_error): relative errors of estimated shares against exact ones."""
    both = share_scores(nbr).select("p1", "p2", F.col("share").alias("x")).join(estimate.select("p1", "p2", F.col("share").alias("y")), ["p1", "p2"])
    e = F.abs(F.col("y") - F.col("x")) / F.col("x")
    return both.agg(F.count("*").alias("pairs"), F.avg(e).alias("mean_error"), F.max(e).alias("worst_error"))
