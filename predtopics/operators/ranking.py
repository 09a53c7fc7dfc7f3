"""Topic ranking by five criteria and their mean rank."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .graph import concept_degree, predicate_degree, rank_concepts, rank_predicates, topic_density
from .tree import topic_concepts

CRITERIA = ("top_predicates", "top_concepts", "similarity", "width", "density")


def crit_predicates(members: DataFrame, ranks: DataFrame, top_n: int = 20, top_frac: float | None = None) -> DataFrame:
    """(topic, top_predicates): how many of the top predicates a topic has."""
    limit = F.lit(top_n) if top_frac is None else F.ceil(F.count("*").over(W.partitionBy()) * top_frac)
    top = ranks.withColumn("__t", F.col("rank") <= limit).select("p", "__t")
    return members.join(top, "p", "left").groupBy("topic").agg(F.count_if(F.coalesce("__t", F.lit(False))).alias("top_predicates"))


def crit_concepts(concepts: DataFrame, edges: DataFrame, members: DataFrame, top_n: int = 20, dedupe: str = "best") -> DataFrame:
    """(topic, top_concepts): how many of the top concepts, each counted in the topic where most of its predicates are (best), nowhere if in several (drop_shared), or in all (none)."""
    nbr = edges.select("p", F.explode(F.array("sc", "oc")).alias("concept")).distinct()
    inside = members.select("topic", "p").join(nbr, "p").groupBy("topic", "concept").agg(F.count("*").alias("n"))
    if dedupe == "best":
        inside = inside.withColumn("__r", F.row_number().over(W.partitionBy("concept").orderBy(F.desc("n"), "topic"))).where("__r = 1")
    elif dedupe == "drop_shared":
        inside = inside.withColumn("__n", F.count("*").over(W.partitionBy("concept"))).where("__n = 1")
    top = rank_concepts(concept_degree(edges), top_n).select("concept", F.lit(True).alias("__t"))
    hits = inside.join(top, "concept").groupBy("topic").agg(F.count("*").alias("top_concepts"))
    return concepts.select("topic").distinct().join(hits, "topic", "left").select("topic", F.coalesce("top_concepts", F.lit(0)).alias("top_concepts"))


def crit_similarity(members: DataFrame, sm: DataFrame) -> DataFrame:
    """(topic, similarity): mean similarity of ordered pairs inside a topic, absent ones 0; null for one predicate."""
    size = members.groupBy("topic").agg(F.count("*").alias("n"))
    a, b = members.select("topic", F.col("p").alias("p1")), members.select("topic", F.col("p").alias("p2"))
    total = sm.where("p1 <> p2").select("p1", "p2", "sm").join(a, "p1").join(b, ["topic", "p2"]).groupBy("topic").agg(F.sum("sm").alias("s"))
    return size.join(total, "topic", "left").select("topic", F.when(F.col("n") > 1, F.coalesce("s", F.lit(0.0)) / (F.col("n") * (F.col("n") - 1))).alias("similarity"))


def criteria(edges: DataFrame, members: DataFrame, sm: DataFrame, widths: DataFrame, top_n: int = 20, dedupe: str = "best", density_kind: str = "simple") -> DataFrame:
    """(topic, and the five criteria). widths: (topic, sw)."""
    one = crit_predicates(members, rank_predicates(predicate_degree(edges), None), top_n)
    out = one.join(crit_concepts(topic_concepts(edges, members), edges, members, top_n, dedupe), "topic").join(crit_similarity(members, sm), "topic")
    out = out.join(widths.select("topic", F.col("sw").alias("width")), "topic", "left")
    return out.join(topic_density(edges, members, density_kind).select("topic", "density"), "topic", "left")


def integrated_rank(crit: DataFrame, weights: dict[str, float] | None = None, missing: str = "last", digits: int = 9) -> DataFrame:
    """Each criterion's rank (ties share, highest first), their weighted mean, and the overall rank (ties by topic). A missing criterion ranks last, or is skipped."""
    weights = weights or {}
    total, mass = F.lit(0.0), F.lit(0.0)
    for c in CRITERIA:
        crit = crit.withColumn(f"rank_{c}", F.rank().over(W.orderBy(F.desc_nulls_last(F.round(c, digits)))))
        w = F.lit(float(weights.get(c, 1.0)))
        w = F.when(F.col(c).isNull(), 0.0).otherwise(w) if missing == "skip" else w
        total, mass = total + w * F.col(f"rank_{c}"), mass + w
    crit = crit.withColumn("mean_rank", F.round(total / mass, digits))
    return crit.withColumn("overall", F.row_number().over(W.orderBy("mean_rank", "topic")))


def top_table(edges: DataFrame, members: DataFrame, top_n: int = 20) -> DataFrame:
    """(rank, p, io, topic, concept, concept_rank): top predicates, their topics, and the concept of the same name if there is one."""
    preds = rank_predicates(predicate_degree(edges), top_n).select("rank", "p", "io")
    concepts = rank_concepts(concept_degree(edges), None).select("concept", F.col("rank").alias("concept_rank"))
    named = preds.join(members.select("topic", "p"), "p", "left")
    return named.join(concepts, F.lower("p") == F.lower("concept"), "left").select("rank", "p", "io", "topic", "concept", "concept_rank")
