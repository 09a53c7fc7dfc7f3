"""Silhouettes against sibling clusters, and widths weighted by size."""

from __future__ import annotations

from pyspark.ml.evaluation import ClusteringEvaluator
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def silhouette(dis: DataFrame, assign: DataFrame, form: str = "ratio") -> DataFrame:
    """(p, cluster, parent, a, b, sibling, sw).

    dis: (p1, p2, d) of ordered pairs; assign: (p, cluster, parent). a is the mean to the others of the own cluster, b the least mean to a
    sibling cluster (same parent), sibling that cluster. A predicate alone in its cluster, or without siblings, has sw 0. form: ratio or cases.
    """
    mine = assign.select(F.col("p").alias("p1"), F.col("cluster").alias("c1"), F.col("parent").alias("g1"))
    other = assign.select(F.col("p").alias("p2"), F.col("cluster").alias("c2"), F.col("parent").alias("g2"))
    met = dis.join(mine, "p1").join(other, "p2").where("g1 = g2")
    means = met.groupBy("p1", "c1", "g1", "c2").agg(F.avg("d").alias("m"))
    out = means.groupBy("p1").agg(F.max(F.when(F.col("c1") == F.col("c2"), F.col("m"))).alias("a"), F.min(F.when(F.col("c1") != F.col("c2"), F.struct("m", "c2"))).alias("near"))
    rows = assign.join(out, F.col("p") == F.col("p1"), "left").select("p", "cluster", "parent", "a", F.col("near.m").alias("b"), F.col("near.c2").alias("sibling"))
    a, b = F.col("a"), F.col("b")
    if form == "cases":
        sw = F.when(a < b, 1 - a / b).when(a == b, 0.0).otherwise(b / a - 1)
    else:
        top = F.greatest("a", "b")
        sw = F.when(top > 0, (b - a) / top).otherwise(0.0)
    return rows.withColumn("sw", F.when(a.isNull() | b.isNull(), 0.0).otherwise(sw))


def silhouette_class(rows: DataFrame, eps: float = 0.1) -> DataFrame:
    """placed: how a predicate lies, by its sw: well, border or misplaced."""
    return rows.withColumn("placed", F.when(F.col("sw") > eps, "well").when(F.col("sw") < -eps, "misplaced").otherwise("border"))


def topic_width(rows: DataFrame) -> DataFrame:
    """(parent, topic, sw, n): mean sw and size of each cluster."""
    return rows.groupBy("parent", F.col("cluster").alias("topic")).agg(F.avg("sw").alias("sw"), F.count("*").alias("n"))


def overall_width(rows: DataFrame) -> DataFrame:
    return rows.agg(F.avg("sw").alias("sw"), F.count("*").alias("n"))


def sibling_width(widths: DataFrame) -> DataFrame:
    """(parent, nsw, k, n): widths of the topics of one parent, weighted by their sizes."""
    return widths.groupBy("parent").agg((F.sum(F.col("sw") * F.col("n")) / F.sum("n")).alias("nsw"), F.count("*").alias("k"), F.sum("n").alias("n"))


def silhouette_fast(features: DataFrame, assign: DataFrame) -> float:
    """Mean squared-Euclid silhouette in time linear in rows and clusters: features (p, features), assign (p, cluster)."""
    rows = features.join(assign, "p").select(array_to_vector("features").alias("features"), F.col("cluster").cast("double").alias("prediction"))
    return ClusteringEvaluator().evaluate(rows)


def silhouette_sample(dis: DataFrame, assign: DataFrame, frac: float, seed: int = 0) -> DataFrame:
    """(n, sw, half): mean sw over a share of the predicates, by hash, and half its 95 % interval."""
    pick = F.substring(F.md5(F.concat("p", F.lit(f"/{seed}")).cast("binary")), 1, 8) < f"{min(int(frac * 2**32), 2**32 - 1):08x}"
    chosen = assign.where(pick).select(F.col("p").alias("p1"))
    rows = silhouette(dis.join(chosen, "p1", "left_semi"), assign).join(chosen, F.col("p") == F.col("p1"), "left_semi")
    return rows.agg(F.count("*").alias("n"), F.avg("sw").alias("sw"), (1.96 * F.stddev("sw") / F.sqrt(F.count("*"))).alias("half"))
