"""Queries woven from a topic: a walk over similar predicates, and the query graph that it gives."""

from __future__ import annotations

import re
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .patterns import Filter, Pattern, QueryGraph

WALK = "topic string, seed string, beta double, step int, p string, via string, sm double"


def topic_graph(edges: DataFrame, members: DataFrame) -> DataFrame:
    """(topic, sc, p, oc): the part of the schema graph that a topic's predicates make."""
    return members.select("topic", "p").join(edges.select("sc", "p", "oc"), "p").select("topic", "sc", "p", "oc").distinct()


def seeds(members: DataFrame, deg: DataFrame, n: int = 1) -> DataFrame:
    """(topic, rank, p): predicates of highest degree to start from, ties by name."""
    from pyspark.sql import Window as W

    ranked = members.select("topic", "p").join(deg.select("p", "io"), "p").withColumn("rank", F.row_number().over(W.partitionBy("topic").orderBy(F.desc("io"), "p")))
    return ranked.where(F.col("rank") <= n).select("topic", "rank", "p")


def walk(pairs: list[tuple[str, str, float]], seed: str, beta: float, max_preds: int | None = None) -> list[tuple[int, str, str | None, float | None]]:
    """(step, p, via, sm): breadth first from the seed; each predicate's neighbours in falling similarity, as long as it is above beta."""
    around: dict[str, list[tuple[float, str]]] = {}
    for a, b, s in pairs:
        if a != b and s > beta:
            around.setdefault(a, []).append((-s, b))
    out, seen, queue = [(1, seed, None, None)], {seed}, [seed]
    for p in queue:
        for s, b in sorted(around.get(p, ())):
            if b not in seen and (max_preds is None or len(out) < max_preds):
                seen.add(b)
                queue.append(b)
                out.append((len(out) + 1, b, p, -s))
    return out


def weave_all(members: DataFrame, sm: DataFrame, deg: DataFrame, n_seeds: int = 1, betas: tuple[float, ...] = (0.2,), max_preds: int | None = None) -> DataFrame:
    """Walks of every topic, seed and beta, one grouped map a topic: (topic, seed, beta, step, p, via, sm)."""
    starts = seeds(members, deg, n_seeds).groupBy("topic").agg(F.collect_list(F.struct("rank", "p")).alias("starts"))
    a, b = members.select("topic", F.col("p").alias("p1")), members.select("topic", F.col("p").alias("p2"))
    inside = members.select("topic", F.col("p").alias("p1"), F.col("p").alias("p2"), F.lit(1.0).alias("sm")).unionByName(sm.where("p1 <> p2").select("p1", "p2", "sm").join(a, "p1").join(b, ["topic", "p2"]).select("topic", "p1", "p2", "sm"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        topic, pairs = pdf["topic"].iloc[0], list(zip(pdf["p1"], pdf["p2"], pdf["sm"]))
        first = sorted((s["rank"], s["p"]) for s in pdf["starts"].iloc[0])
        rows = [(topic, seed, beta, *w) for _, seed in first for beta in betas for w in walk(pairs, seed, beta, max_preds)]
        return pd.DataFrame(rows, columns=[c.split()[0] for c in WALK.split(", ")])

    return inside.join(starts, "topic").groupBy("topic").applyInPandas(run, WALK)


def weave(members: DataFrame, sm: DataFrame, deg: DataFrame, topic: str, beta: float = 0.2, max_preds: int | None = None) -> DataFrame:
    return weave_all(members.where(F.col("topic") == topic), sm, deg, 1, (beta,), max_preds)


def degree_query(members: DataFrame, deg: DataFrame, n: int = 3) -> DataFrame:
    """(topic, step, p): the n predicates of highest degree, similarity aside."""
    return seeds(members, deg, n).select("topic", F.col("rank").alias("step"), "p")


def variable(concept: str) -> str:
    return "?" + re.sub(r"\W", "_", concept[:1].lower() + concept[1:])


def to_query_graph(steps: list[str], edges: list[tuple[str, str, str]]) -> QueryGraph:
    """A query graph of walked predicates, in order: a variable for each concept, the same for predicates that share it.

    Of a predicate's schema edges the one that touches concepts already in the query is taken, else the first by name.
    """
    patterns, used = [], []
    for p in steps:
        mine = sorted(e for e in edges if e[1] == p)
        if not mine:
            continue
        sc, _, oc = max(mine, key=lambda e: ((e[0] in used) + (e[2] in used), [-ord(c) for c in e[0] + e[2]]))
        used += [c for c in (sc, oc) if c not in used]
        right = variable(oc) if oc != sc else variable(oc) + "2"
        patterns.append(Pattern(variable(sc), p, right))
    q = QueryGraph(tuple(dict.fromkeys(v for x in patterns for v in x.variables())), tuple(patterns))
    return replace(q, types=tuple((variable(c), c) for c in used if any(e[0] == c for e in edges)))


def decorate(q: QueryGraph, types: bool = True, labels: dict[str, str] | None = None) -> QueryGraph:
    """With or without type patterns, and with a label variable for each of ``labels``: variable -> predicate that names it."""
    extra = tuple(Pattern(v, p, v + "Label") for v, p in (labels or {}).items())
    shown = tuple(v + "Label" if v in (labels or {}) else v for v in q.select)
    return replace(q, types=q.types if types else (), patterns=q.patterns + extra, select=shown)


def pairwise(q: QueryGraph, entity: str, strict: bool = True) -> QueryGraph:
    """The same links for a second entity. strict: required, and the two differ; literal: optional, and they need not."""
    second = entity + "2"
    other = [replace(x, s=second if x.s == entity else x.s, o=second if x.o == entity else x.o) for x in q.patterns if entity in (x.s, x.o)]
    if strict:
        return replace(q, select=(*q.select, second), patterns=q.patterns + tuple(other), filters=(*q.filters, Filter(entity, "!=", second)))
    base = max((x.optional for x in q.patterns), default=0)
    return replace(q, select=(*q.select, second), patterns=q.patterns + tuple(replace(x, optional=base + 1 + n) for n, x in enumerate(other)), types=q.types + tuple((second, c) for v, c in q.types if v == entity))


def add_query(q: QueryGraph, other: QueryGraph) -> QueryGraph:
    """Both queries in one; equal variables are the same thing."""
    both = lambda a, b: tuple(dict.fromkeys((*a, *b)))
    return replace(q, select=both(q.select, other.select), patterns=both(q.patterns, other.patterns), types=both(q.types, other.types), filters=both(q.filters, other.filters))


def drop_pattern(q: QueryGraph, p: str) -> QueryGraph:
    """Without the patterns of a predicate, and without variables that nothing binds any more."""
    kept = tuple(x for x in q.patterns if x.p != p)
    bound = {v for x in kept for v in x.variables()}
    return replace(q, patterns=kept, select=tuple(v for v in q.select if v in bound), types=tuple(t for t in q.types if t[0] in bound), filters=tuple(f for f in q.filters if f.variables() <= bound))


def graph_export(edges: DataFrame, q: QueryGraph | None = None) -> tuple[DataFrame, DataFrame]:
    """(nodes: id, kind, lit), (links: source, target, lit) of a graph, with what the query uses lit."""
    preds = [x.p for x in q.patterns] if q else []
    lit = F.col("p").isin(*preds) if preds else F.lit(False)
    links = edges.select(F.col("sc").alias("source"), F.col("p").alias("target"), lit.alias("lit")).unionByName(edges.select(F.col("p").alias("source"), F.col("oc").alias("target"), lit.alias("lit")))
    nodes = edges.select(F.col("p").alias("id"), F.lit("predicate").alias("kind"), lit.alias("lit")).unionByName(edges.select(F.explode(F.array("sc", "oc")).alias("id"), F.lit("concept").alias("kind"), lit.alias("lit")))
    return nodes.groupBy("id", "kind").agg(F.bool_or("lit").alias("lit")), links.groupBy("source", "target").agg(F.bool_or("lit").alias("lit"))
