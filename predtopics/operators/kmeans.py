"""K-means over matrix rows: relational, as a whole-level sweep of grouped maps, and by the ML library."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..settle import settle
from . import local


def long_rows(features: DataFrame) -> DataFrame:
    """(p, features) -> (p, dim, x)."""
    return features.select("p", F.posexplode("features").alias("dim", "x"))


def lloyd(rows: DataFrame, start: DataFrame, max_iter: int = 20, digits: int = 9) -> tuple[DataFrame, DataFrame]:
    """((p, cluster), (cluster, dim, x)) from (p, dim, x) rows and (cluster, p) starting rows. Distances are rounded, ties go to the smaller cluster."""
    centres = settle(start.join(rows, "p").select("cluster", "dim", "x"))
    assign, state = None, None
    for _ in range(max_iter):
        square = F.pow(F.col("x") - F.col("y"), 2)
        d = rows.join(F.broadcast(centres.select("cluster", "dim", F.col("x").alias("y"))), "dim").groupBy("p", "cluster").agg(F.round(F.sum(square), digits).alias("d"))
        assign = settle(d.groupBy("p").agg(F.min(F.struct("d", "cluster")).alias("b")).select("p", F.col("b.cluster").alias("cluster")))
        now = assign.agg(F.sum(F.pmod(F.xxhash64("p", "cluster"), F.lit(1 << 40)))).first()[0]
        if now == state:
            break
        state = now
        centres = settle(rows.join(assign, "p").groupBy("cluster", "dim").agg(F.avg("x").alias("x")))
    return assign, centres


def top_degree_start(deg: DataFrame, k: int) -> DataFrame:
    """(cluster, p): the k predicates of highest degree, ties by name."""
    return deg.withColumn("cluster", F.row_number().over(W.orderBy(F.desc("io"), "p")) - 1).where(F.col("cluster") < k).select("cluster", "p")


def inertia(rows: DataFrame, assign: DataFrame, centres: DataFrame) -> DataFrame:
    """(cluster, cost)."""
    both = rows.join(assign, "p").join(centres.select("cluster", "dim", F.col("x").alias("y")), ["cluster", "dim"])
    return both.groupBy("cluster").agg(F.sum(F.pow(F.col("x") - F.col("y"), 2)).alias("cost"))


def ml_kmeans(features: DataFrame, k: int, seed: int = 1, max_iter: int = 50) -> DataFrame:
    """(p, cluster) by the ML library, started by its parallel seeding."""
    rows = features.select("p", array_to_vector("features").alias("features"))
    return KMeans(k=k, seed=seed, maxIter=max_iter).fit(rows).transform(rows).select("p", F.col("prediction").alias("cluster"))


SWEEP = "topic string, k int, restart int, n_clusters int, inertia double, nsw double, ps array<string>, labels array<int>, sws array<double>"


def _weights(x: np.ndarray, how: str) -> np.ndarray:
    if how == "variance":
        return x.var(0)
    if how == "mean_sim":
        return x.mean(0)
    return np.ones(x.shape[1])


def level_sweep(members: DataFrame, features: DataFrame, ks: tuple[int, ...], restarts: int = 1, init: str = "spread", dissimilarity: str = "row_sqeuclid", features_of: str = "global", feature_weight: str = "none", seed: int = 7, deg: DataFrame | None = None, eps: float = 1e-3) -> DataFrame:
    """Every (topic, k, restart) of a level as one job: labels, inertia and silhouettes against siblings.

    members: (topic, p); features: (p, features) whole matrix rows over sorted predicate names. One task holds one topic's rows, which
    cross the shuffle once and whose dissimilarities are made once for all k.
    """
    names = features.select("p").distinct().agg(F.array_sort(F.collect_list("p")).alias("names"))
    rows = members.join(features, "p").crossJoin(F.broadcast(names)).withColumn("at", F.array_position("names", F.col("p")) - 1).drop("names")
    rows = rows.join(deg.select("p", "io"), "p", "left") if deg is not None else rows.withColumn("io", F.lit(0).cast("long"))

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:  # noqa: ANN001
        pdf = pdf.sort_values("p")
        whole, at, degree = np.stack(pdf["features"].to_numpy()), pdf["at"].to_numpy(), pdf["io"].to_numpy()
        x = whole[:, at] if features_of == "topic" else whole
        x = x * np.sqrt(_weights(x, feature_weight))
        d, out = local.dissimilarities(whole, at, dissimilarity, eps), []
        for k in (k for k in ks if k < len(pdf)):
            for restart in range(restarts):
                labels, cost = local.lloyd(x, k, init, seed * 1000 + restart, degree)
                sw = local.silhouette(d, labels)
                out.append({"topic": key[0], "k": k, "restart": restart, "n_clusters": len(np.unique(labels)), "inertia": cost, "nsw": float(sw.mean()), "ps": pdf["p"].tolist(), "labels": labels.tolist(), "sws": sw.tolist()})
        return pd.DataFrame(out, columns=[c.split()[0] for c in SWEEP.split(", ")])

    return rows.groupBy("topic").applyInPandas(run, SWEEP)
