"""Terms across domains: closeness of words, pruned linking, contraction of links, chains between namespaces."""

from __future__ import annotations

import re

from pyspark.ml.feature import Word2Vec
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..settle import settle
from . import vectors


def cosine(a, b):  # noqa: ANN001, ANN201
    """Cosine of two array columns."""
    dot = F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    norm = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    return dot / (norm(a) * norm(b))


def words(name):  # noqa: ANN001, ANN201
    """Lower-case words of an identifier in camel case or with separators."""
    return F.filter(F.split(F.lower(F.regexp_replace(name, "([a-z])([A-Z])", "$1 $2")), r"[^a-z0-9]+"), lambda w: w != "")


def normalise_terms(edges: DataFrame, min_cos: float = 0.9, size: int = 16, seed: int = 3) -> DataFrame:
    """(c1, c2, cos): concepts whose contexts (the predicates and concepts around them) give close word vectors."""
    around = edges.select(F.concat(words("sc"), words("p"), words("oc")).alias("w"))
    model = Word2Vec(vectorSize=size, minCount=1, seed=seed, inputCol="w", outputCol="v", numPartitions=1, maxIter=5).fit(around)
    concepts = edges.select(F.explode(F.array("sc", "oc")).alias("c")).distinct().withColumn("w", words("c"))
    v = settle(model.transform(concepts).select("c", vector_to_array("v").alias("v")))
    a, b = v.select(F.col("c").alias("c1"), F.col("v").alias("v1")), v.select(F.col("c").alias("c2"), F.col("v").alias("v2"))
    return a.join(b, F.col("c1") < F.col("c2")).withColumn("cos", cosine(F.col("v1"), F.col("v2"))).where(F.col("cos") >= min_cos).select("c1", "c2", "cos")


def link_terms(a: DataFrame, b: DataFrame, radius: float, pivots: int = 4, seed: int = 1) -> DataFrame:
    """(id1, id2, d) with distance up to radius, of (id, v) rows: by the triangle inequality only pairs whose distances to all pivots differ by radius or less are measured.

    Rows meet in blocks, which are ranges of the first pivot's distance; blocks that the pivots hold apart do not meet.
    """
    dist = lambda x, y: F.sqrt(F.aggregate(F.zip_with(x, y, lambda s, t: F.pow(s.cast("double") - t.cast("double"), 2.0)), F.lit(0.0), lambda s, t: s + t))
    chosen = a.where(F.col("v").isNotNull()).orderBy(F.xxhash64("id", F.lit(seed))).limit(pivots).collect()
    if not chosen:
        return a.limit(0).select(F.col("id").alias("id1")).crossJoin(b.limit(0).select(F.col("id").alias("id2"))).withColumn("d", F.lit(0.0))
    at = lambda df: df.select("id", "v", F.array(*[dist(F.col("v"), F.array(*[F.lit(float(x)) for x in r["v"]])) for r in chosen]).alias("far"))
    return vectors.within(at(a), at(b), radius, len(chosen))


def contract_same(links: DataFrame) -> DataFrame:
    """(term, name): terms tied by same-as links (a, b), each with the least of its class; labels spread until none changes."""
    both = settle(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    now = settle(both.select(F.col("a").alias("term")).distinct().withColumn("name", F.col("term")))
    while True:
        least = both.join(now.select(F.col("term").alias("b"), F.col("name").alias("n")), "b").groupBy("a").agg(F.min("n").alias("n"))
        hop = now.join(least, F.col("term") == F.col("a"), "left").select("term", F.col("name").alias("old"), F.least("name", F.coalesce("n", "name")).alias("name"))
        jump = hop.join(now.select(F.col("term").alias("t"), F.col("name").alias("n2")), F.col("name") == F.col("t"), "left").select("term", "old", F.least("name", F.coalesce("n2", "name")).alias("name"))
        new = settle(jump)
        now = new.select("term", "name")
        if new.where("old <> name").isEmpty():
            return now


def rewrite_terms(facts: DataFrame, names: DataFrame) -> DataFrame:
    """Facts with subjects and objects put by the names of their classes."""
    s, o = names.select(F.col("term").alias("s"), F.col("name").alias("__s")), names.select(F.col("term").alias("o"), F.col("name").alias("__o"))
    out = facts.join(s, "s", "left").join(o, "o", "left").withColumn("s", F.coalesce("__s", "s")).withColumn("o", F.coalesce("__o", "o"))
    return out.select(*facts.columns).distinct()


def cross_domain_chains(sm: DataFrame, ns: DataFrame) -> DataFrame:
    """Pairs of the matrix whose predicates no namespace has in common: (p1, p2, l, sm, ns1, ns2). ns: (p, ns)."""
    sets = ns.groupBy("p").agg(F.array_sort(F.collect_set("ns")).alias("s"))
    both = sm.where("p1 < p2").join(sets.select(F.col("p").alias("p1"), F.col("s").alias("s1")), "p1").join(sets.select(F.col("p").alias("p2"), F.col("s").alias("s2")), "p2")
    return both.where(~F.arrays_overlap("s1", "s2")).select("p1", "p2", "l", "sm", F.concat_ws("+", "s1").alias("ns1"), F.concat_ws("+", "s2").alias("ns2"))


def local_name(term: str) -> str:
    return re.split(r"[/#:]", term)[-1]


def endpoint_stats(edges: DataFrame) -> DataFrame:
    """(p, facts, subjects_of, objects_of): what a service would tell about each predicate."""
    return edges.groupBy("p").agg(F.sum("n_facts").alias("facts"), F.count_distinct("sc").alias("subjects_of"), F.count_distinct("oc").alias("objects_of"))
