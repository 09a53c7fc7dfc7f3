"""Clusterers to compare with, and curves of width over k."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.ml.clustering import BisectingKMeans, PowerIterationClustering
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..settle import settle
from . import local
from .similarity import concept_similarity, row_features

ALGORITHMS = ("kmeans", "medoids", "sampled_medoids", "single", "complete", "average", "ward", "divisive", "random")


def _labels(algorithm: str, x: np.ndarray, d: np.ndarray, k: int, seed: int) -> np.ndarray:
    if algorithm == "kmeans":
        return local.lloyd(x, k, "spread", seed)[0]
    if algorithm == "medoids":
        return local.medoids(d, k)[0]
    if algorithm == "sampled_medoids":
        return local.sampled_medoids(d, k, seed=seed)[0]
    if algorithm == "divisive":
        return local.divide(d, k)
    if algorithm == "random":
        return np.random.default_rng(seed).permutation(np.arange(len(d)) % k)
    return local.cut(local.agglomerate(d**2 if algorithm == "ward" else d, algorithm), len(d), k)


def clusterings(features: DataFrame, algorithms: tuple[str, ...] = ALGORITHMS, ks: tuple[int, ...] = (2, 3, 4, 5, 6, 7, 8), dissimilarity: str = "row_sqeuclid", seed: int = 7) -> DataFrame:
    """(algorithm, k, p, cluster, sw): each algorithm and k is a task of its own over all rows (at most thousands)."""
    names = features.agg(F.array_sort(F.collect_list("p")).alias("names"))
    grid = features.sparkSession.createDataFrame([(a, k) for a in algorithms for k in ks], "algorithm string, k int")
    rows = features.crossJoin(F.broadcast(names)).withColumn("at", F.array_position("names", F.col("p")) - 1).drop("names").crossJoin(F.broadcast(grid))

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:  # noqa: ANN001
        pdf = pdf.sort_values("p")
        x, at = np.stack(pdf["features"].to_numpy()), pdf["at"].to_numpy()
        d = local.dissimilarities(x, at, dissimilarity)
        labels = np.unique(_labels(key[0], x, d, min(key[1], len(x)), seed), return_inverse=True)[1]
        return pd.DataFrame({"algorithm": key[0], "k": key[1], "p": pdf["p"], "cluster": labels.astype(np.int32), "sw": local.silhouette(d, labels)})

    return rows.groupBy("algorithm", "k").applyInPandas(run, "algorithm string, k int, p string, cluster int, sw double")


def width_curve(features: DataFrame, algorithms: tuple[str, ...] = ALGORITHMS, ks: tuple[int, ...] = tuple(range(2, 17)), dissimilarity: str = "row_sqeuclid") -> DataFrame:
    """(algorithm, k, clusters, sw)."""
    return clusterings(features, algorithms, ks, dissimilarity).groupBy("algorithm", "k").agg(F.count_distinct("cluster").alias("clusters"), F.avg("sw").alias("sw"))


def node_curves(members: DataFrame, features: DataFrame, algorithms: tuple[str, ...] = ALGORITHMS, ks: tuple[int, ...] = tuple(range(2, 17)), dissimilarity: str = "row_sqeuclid", seed: int = 7) -> DataFrame:
    """(topic, algorithm, k, clusters, sw): width_curve of the predicates of each topic in members (topic, p); each topic, algorithm and k is a task of its own."""
    names = features.agg(F.array_sort(F.collect_list("p")).alias("names"))
    grid = features.sparkSession.createDataFrame([(a, k) for a in algorithms for k in ks], "algorithm string, k int")
    rows = members.join(features, "p").crossJoin(F.broadcast(names)).withColumn("at", F.array_position("names", F.col("p")) - 1).drop("names").crossJoin(F.broadcast(grid))

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:  # noqa: ANN001
        topic, algorithm, k = key
        pdf = pdf.sort_values("p")
        x, at = np.stack(pdf["features"].to_numpy()), pdf["at"].to_numpy()
        d = local.dissimilarities(x, at, dissimilarity)
        labels = np.unique(_labels(algorithm, x, d, min(k, len(x)), seed), return_inverse=True)[1]
        return pd.DataFrame({"topic": [topic], "algorithm": [algorithm], "k": [k], "clusters": [len(np.unique(labels))], "sw": [float(local.silhouette(d, labels).mean())]})

    return rows.groupBy("topic", "algorithm", "k").applyInPandas(run, "topic string, algorithm string, k int, clusters long, sw double")


def stability(curve: DataFrame) -> DataFrame:
    """(algorithm, best, span, sd): how an algorithm's width varies over k."""
    return curve.groupBy("algorithm").agg(F.max("sw").alias("best"), (F.max("sw") - F.min("sw")).alias("span"), F.stddev("sw").alias("sd"))


def bisecting(features: DataFrame, k: int, seed: int = 1) -> DataFrame:
    rows = features.select("p", array_to_vector("features").alias("features"))
    return BisectingKMeans(k=k, seed=seed).fit(rows).transform(rows).select("p", F.col("prediction").alias("cluster"))


def power_iteration(sm: DataFrame, k: int) -> DataFrame:
    """Power-iteration clustering of the matrix as a weighted graph."""
    ids = sm.select(F.col("p1").alias("p")).distinct().withColumn("id", F.row_number().over(W.orderBy("p")).cast("long"))
    links = sm.where("p1 < p2").join(ids.select(F.col("p").alias("p1"), F.col("id").alias("src")), "p1").join(ids.select(F.col("p").alias("p2"), F.col("id").alias("dst")), "p2")
    found = PowerIterationClustering(k=k, maxIter=20, weightCol="sm").assignClusters(links.select("src", "dst", "sm"))
    return found.join(ids, "id").select("p", "cluster")


def random_partition(preds: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """Parts of equal size by hash order."""
    rank = F.row_number().over(W.orderBy(F.md5(F.concat("p", F.lit(f"/{seed}")).cast("binary")), "p"))
    return preds.select("p").distinct().select("p", F.pmod(rank - 1, F.lit(k)).alias("cluster"))


def spanning_tree(dis: DataFrame) -> DataFrame:
    """(a, b, d): minimum spanning tree by Boruvka rounds of joins; single linkage at any size. dis: (p1, p2, d), any direction."""
    edges = settle(dis.select(F.least("p1", "p2").alias("a"), F.greatest("p1", "p2").alias("b"), "d").where("a <> b").distinct())
    comp = settle(edges.select(F.explode(F.array("a", "b")).alias("p")).distinct().withColumn("c", F.col("p")))
    tree = None
    while True:
        now = edges.join(comp.select(F.col("p").alias("a"), F.col("c").alias("ca")), "a").join(comp.select(F.col("p").alias("b"), F.col("c").alias("cb")), "b").where("ca <> cb")
        both = now.select(F.col("ca").alias("c"), "a", "b", "d", F.col("cb").alias("o")).unionByName(now.select(F.col("cb").alias("c"), "a", "b", "d", F.col("ca").alias("o")))
        best = settle(both.groupBy("c").agg(F.min(F.struct("d", "a", "b", "o")).alias("m")).select("c", "m.*"))
        if best.isEmpty():
            break
        picked = best.select("a", "b", "d").distinct()
        tree = picked if tree is None else tree.unionByName(picked)
        names = settle(comp.select("c").distinct().withColumn("r", F.col("c")))
        links = best.select("c", "o").unionByName(best.select(F.col("o").alias("c"), F.col("c").alias("o")))
        while True:
            least = links.join(names.select(F.col("c").alias("o"), F.col("r").alias("ro")), "o").groupBy("c").agg(F.min("ro").alias("ro"))
            new = settle(names.join(least, "c", "left").select("c", F.least("r", F.coalesce("ro", "r")).alias("r"), (F.coalesce("ro", "r") < F.col("r")).alias("moved")))
            names = new.select("c", "r")
            if new.where("moved").isEmpty():
                break
        comp = settle(comp.join(names, "c").select("p", F.col("r").alias("c")))
    return tree.distinct() if tree is not None else edges


def concept_topics(nbr: DataFrame, k: int) -> DataFrame:
    """(p, cluster) of concepts clustered by their own share scores."""
    s = concept_similarity(nbr).select(F.col("c1").alias("p1"), F.col("c2").alias("p2"), F.col("share").alias("sm"))
    names = nbr.select(F.col("concept").alias("p")).distinct()
    rows = s.unionByName(s.select(F.col("p2").alias("p1"), F.col("p1").alias("p2"), "sm")).unionByName(names.select(F.col("p").alias("p1"), F.col("p").alias("p2"), F.lit(1.0).alias("sm")))
    return clusterings(row_features(rows, names), ("kmeans",), (k,)).select("p", "cluster")


def permutation_test(features: DataFrame, assign: DataFrame, rounds: int = 199, dissimilarity: str = "row_sqeuclid", seed: int = 5) -> DataFrame:
    """(sw, mean, p_value, rounds): overall width against partitions of the same sizes at random."""
    rows = features.join(assign.select("p", "cluster"), "p")
    names = features.agg(F.array_sort(F.collect_list("p")).alias("names"))
    rows = rows.crossJoin(F.broadcast(names)).withColumn("at", F.array_position("names", F.col("p")) - 1).drop("names")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("p")
        d = local.dissimilarities(np.stack(pdf["features"].to_numpy()), pdf["at"].to_numpy(), dissimilarity)
        labels, rng = pdf["cluster"].to_numpy(), np.random.default_rng(seed)
        own = local.silhouette(d, labels).mean()
        other = np.array([local.silhouette(d, rng.permutation(labels)).mean() for _ in range(rounds)])
        return pd.DataFrame([{"sw": own, "mean": other.mean(), "p_value": (1 + (other >= own).sum()) / (rounds + 1), "rounds": rounds}])

    return rows.withColumn("__g", F.lit(1)).groupBy("__g").applyInPandas(run, "sw double, mean double, p_value double, rounds int")


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """(n, rand, information): adjusted Rand index and normalised information of two clusterings (p, cluster), from their contingency table alone."""
    table = a.select("p", F.col("cluster").cast("string").alias("x")).join(b.select("p", F.col("cluster").cast("string").alias("y")), "p").groupBy("x", "y").agg(F.count("*").alias("n"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        t = pdf.pivot_table(index="x", columns="y", values="n", aggfunc="sum", fill_value=0).to_numpy(float)
        c2 = lambda v: (v * (v - 1) / 2).sum()
        n = t.sum()
        both, one, two, every = c2(t), c2(t.sum(1)), c2(t.sum(0)), n * (n - 1) / 2
        expected, top = one * two / every, (one + two) / 2
        h = lambda q: float(-(q[q > 0] * np.log(q[q > 0])).sum())
        hx, hy, hxy = h(t.sum(1) / n), h(t.sum(0) / n), h((t / n).ravel())
        return pd.DataFrame([{"n": int(n), "rand": 1.0 if top == expected else (both - expected) / (top - expected), "information": 1.0 if hx + hy == 0 else 2 * (hx + hy - hxy) / (hx + hy)}])

    return table.withColumn("__g", F.lit(1)).groupBy("__g").applyInPandas(run, "n long, rand double, information double")
