"""Measures of the schema graph: patterns, degrees, ranks, densities, statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .ontology import domain_predicates, incidence


def share_patterns(edges: DataFrame) -> DataFrame:
    """(p1, p2, kind, n_shared), p1 < p2: concepts shared as subject, as object, as both, or crosswise (object of one, subject of the other)."""
    inc = incidence(edges)
    left = inc.select(F.col("p").alias("p1"), "concept", F.col("side").alias("s1"))
    pairs = left.join(inc.select(F.col("p").alias("p2"), "concept", F.col("side").alias("s2")), "concept").where("p1 < p2")
    at = pairs.groupBy("p1", "p2", "concept").agg(F.bool_or((F.col("s1") == "in") & (F.col("s2") == "in")).alias("subject"), F.bool_or((F.col("s1") == "out") & (F.col("s2") == "out")).alias("object"), F.bool_or(F.col("s1") != F.col("s2")).alias("cross"))
    kinds = F.filter(F.array(F.when(F.col("subject"), "subject"), F.when(F.col("object"), "object"), F.when(F.col("subject") & F.col("object"), "both"), F.when(F.col("cross"), "cross")), lambda k: k.isNotNull())
    return at.select("p1", "p2", F.explode(kinds).alias("kind")).groupBy("p1", "p2", "kind").agg(F.count("*").alias("n_shared"))


def connection_patterns(edges: DataFrame, max_level: int = 2, direction: str = "forward") -> DataFrame:
    """(p1, p2, level, path): chains of edges in which the object of one is the subject of the next, without a predicate twice; path lists predicates and concepts by turns. Levels from 2."""
    step = edges.select("sc", "p", "oc").distinct()
    if direction == "undirected":
        step = step.unionByName(step.select(F.col("oc").alias("sc"), "p", F.col("sc").alias("oc"))).distinct()
    cur = step.select(F.col("p").alias("p1"), F.col("p").alias("p2"), F.col("oc").alias("end"), F.array("p").alias("path"), F.array("p").alias("seen"))
    out = None
    for level in range(1, max_level + 1):
        grown = cur.join(step.select(F.col("sc").alias("end"), F.col("p").alias("next"), F.col("oc").alias("far")), "end").where(~F.array_contains("seen", F.col("next")))
        cur = grown.select("p1", F.col("next").alias("p2"), F.col("far").alias("end"), F.concat("path", F.array("end", "next")).alias("path"), F.array_append("seen", F.col("next")).alias("seen"))
        found = cur.select("p1", "p2", F.lit(level).alias("level"), "path").distinct()
        if level >= 2:
            out = found if out is None else out.unionByName(found)
    return out if out is not None else cur.select("p1", "p2", F.lit(1).alias("level"), "path").limit(0)


def predicate_degree(edges: DataFrame) -> DataFrame:
    """(p, in_deg, out_deg, io): distinct concepts on either side."""
    inside, outside = F.count_distinct("sc"), F.count_distinct("oc")
    return edges.groupBy("p").agg(inside.alias("in_deg"), outside.alias("out_deg"), (inside + outside).alias("io"))


def concept_degree(edges: DataFrame) -> DataFrame:
    """(concept, in_deg, out_deg, io): distinct predicates that end in it and that start from it."""
    inc = incidence(edges).groupBy("concept").agg(F.count_if(F.col("side") == "out").alias("in_deg"), F.count_if(F.col("side") == "in").alias("out_deg"))
    return inc.withColumn("io", F.col("in_deg") + F.col("out_deg"))


def rank_predicates(deg: DataFrame, top: int | None = 20) -> DataFrame:
    """Ranks 1..n, ties by name."""
    out = deg.withColumn("rank", F.row_number().over(W.orderBy(F.desc("io"), "p")))
    return out.where(F.col("rank") <= top) if top else out


def rank_concepts(deg: DataFrame, top: int | None = 20) -> DataFrame:
    """Ties share a rank."""
    out = deg.withColumn("rank", F.rank().over(W.orderBy(F.desc("io"))))
    return out.where(F.col("rank") <= top) if top else out


def term_frequency(edges: DataFrame, by: str = "p") -> DataFrame:
    """(by, n, share): facts of each predicate, or of each concept on either side."""
    rows = edges.select(F.col("p").alias(by), "n_facts") if by == "p" else edges.select(F.explode(F.array("sc", "oc")).alias(by), "n_facts")
    n = rows.groupBy(by).agg(F.sum("n_facts").alias("n"))
    return n.withColumn("share", F.col("n") / F.sum("n").over(W.partitionBy()))


def _density(e, c, p, kind: str):  # noqa: ANN001, ANN202
    v = c + p
    room = v * (c - 1) * (p - 1) if kind == "printed" else v * (v - 1)
    return F.when(room > 0, 2 * e / room)


def density(edges: DataFrame, kind: str = "simple") -> DataFrame:
    """One row (e, c, p, density). simple: links over pairs of nodes; printed: the other published form; null where it has no value."""
    inc = incidence(edges)
    n = inc.agg(F.count("*").alias("e"), F.count_distinct("concept").alias("c"), F.count_distinct("p").alias("p"))
    return n.withColumn("density", _density(F.col("e"), F.col("c"), F.col("p"), kind))


def topic_density(edges: DataFrame, members: DataFrame, kind: str = "simple") -> DataFrame:
    """(topic, e, c, p, density) of each topic's own part of the graph."""
    inc = incidence(edges).join(members.select("topic", "p"), "p")
    n = inc.groupBy("topic").agg(F.count("*").alias("e"), F.count_distinct("concept").alias("c"), F.count_distinct("p").alias("p"))
    return n.withColumn("density", _density(F.col("e"), F.col("c"), F.col("p"), kind))


def ontology_stats(edges: DataFrame) -> DataFrame:
    """(feature, value): sizes of the graph and its densities."""
    dom, inc = domain_predicates(edges), incidence(domain_predicates(edges))
    total = edges.agg(F.count("*").alias("schema_edges"), F.sum("n_facts").alias("facts"), F.count_distinct("p").alias("predicates"))
    own = dom.agg(F.sum("n_facts").alias("domain_facts"), F.count_distinct("p").alias("domain_predicates"), F.count_distinct("ns").alias("namespaces"))
    links = inc.agg(F.count("*").alias("links"), F.count_distinct("concept").alias("concepts"))
    wide = total.crossJoin(own).crossJoin(links)
    for kind in ("simple", "printed"):
        wide = wide.withColumn(f"density_{kind}", F.round(_density(F.col("links"), F.col("concepts"), F.col("domain_predicates"), kind), 9))
    return wide.select(F.explode(F.map_from_arrays(F.array(*[F.lit(c) for c in wide.columns]), F.array(*[F.col(c).cast("double") for c in wide.columns]))).alias("feature", "value"))


def namespace_table(edges: DataFrame) -> DataFrame:
    """(ns, n_concepts, n_predicates): by the namespace of the table that says it; subject concepts count for their own."""
    return edges.groupBy("ns").agg(F.count_distinct("sc").alias("n_concepts"), F.count_distinct("p").alias("n_predicates"))
