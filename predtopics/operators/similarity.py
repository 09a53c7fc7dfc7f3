"""Similarity of predicates: shared neighbourhoods, chains of intermediate predicates, and the matrix of both.

All are joins on long (p1, p2, value) rows, so absent pairs cost nothing. Chains grow level by level: a frontier of
shortest paths meets the share scores, the best product of each new pair is kept, pairs that are known drop out, and each
level is written to the shared folder.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..settle import settle, small


def _pairs(nbr: DataFrame, method: str, salt: int) -> DataFrame:
    """(p1, p2, n12), p1 < p2, of predicates with a common concept."""
    if method == "collect":
        sets = nbr.groupBy("concept").agg(F.array_sort(F.collect_set("p")).alias("ps")).where(F.size("ps") > 1)
        firsts = sets.select("ps", F.posexplode("ps").alias("i", "p1"))
        both = firsts.select("p1", F.explode(F.slice("ps", F.col("i") + 2, F.size("ps"))).alias("p2"))
    else:
        left, right = nbr.select(F.col("p").alias("p1"), "concept"), nbr.select(F.col("p").alias("p2"), "concept")
        keys = ["concept"]
        if salt > 1:  # a concept that touches very many predicates is met in several tasks
            left = left.withColumn("salt", F.pmod(F.xxhash64("p1"), F.lit(salt)))
            right = right.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salt - 1).cast("long"))))
            keys.append("salt")
        both = left.join(right, keys).where("p1 < p2")
    return both.groupBy("p1", "p2").agg(F.count("*").alias("n12"))


def _mirrored(df: DataFrame) -> DataFrame:
    other = [c for c in df.columns if c not in ("p1", "p2", "n1", "n2")]
    sizes = [c for c in ("n1", "n2") if c in df.columns]
    back = df.select(F.col("p2").alias("p1"), F.col("p1").alias("p2"), *([F.col("n2").alias("n1"), F.col("n1").alias("n2")] if sizes else []), *other)
    return df.select("p1", "p2", *sizes, *other).unionByName(back)


def share_scores(nbr: DataFrame, method: str = "join", salt: int = 1, max_degree: int | None = None, number: str = "double", symmetric: bool = False) -> DataFrame:
    """(p1, p2, n1, n2, n12, share) of pairs with a common concept, p1 < p2 (or both ways): n12 squared over n1 times n2.

    max_degree leaves out concepts of more predicates. number: double, decimal, or rational (columns num, den).
    """
    if max_degree:
        nbr = nbr.withColumn("__d", F.count("*").over(W.partitionBy("concept"))).where(F.col("__d") <= max_degree).drop("__d")
    sizes = small(nbr.groupBy("p").agg(F.count("*").alias("n")))
    both = _pairs(nbr, method, salt).join(sizes.select(F.col("p").alias("p1"), F.col("n").alias("n1")), "p1").join(sizes.select(F.col("p").alias("p2"), F.col("n").alias("n2")), "p2")
    num, den = F.col("n12") * F.col("n12"), F.col("n1") * F.col("n2")
    value = {"double": [(num / den).alias("share")], "decimal": [(num.cast("decimal(18,0)") / den.cast("decimal(18,0)")).cast("decimal(38,18)").alias("share")], "rational": [num.alias("num"), den.alias("den")]}[number]
    out = both.select("p1", "p2", "n1", "n2", "n12", *value)
    return _mirrored(out) if symmetric else out


def overlap_scores(nbr: DataFrame) -> DataFrame:
    """share beside Jaccard, Dice and cosine of the same sets."""
    s = share_scores(nbr)
    n1, n2, n12 = F.col("n1"), F.col("n2"), F.col("n12")
    return s.select("p1", "p2", "share", (n12 / (n1 + n2 - n12)).alias("jaccard"), (2 * n12 / (n1 + n2)).alias("dice"), (n12 / F.sqrt(n1 * n2)).alias("cosine"))


def forward_pairs(edges: DataFrame, share: DataFrame) -> DataFrame:
    """Share scores of pairs in which an object concept of p1 is a subject concept of p2."""
    out = edges.select(F.col("p").alias("p1"), F.col("oc").alias("c")).distinct()
    inn = edges.select(F.col("p").alias("p2"), F.col("sc").alias("c")).distinct()
    return out.join(inn, "c").where("p1 <> p2").select("p1", "p2").distinct().join(share.select("p1", "p2", "share"), ["p1", "p2"])


def chain_scores(share: DataFrame, max_level: int | None = None, min_score: float = 0.0, form: str = "linear") -> DataFrame:
    """(p1, p2, l, chain): of every ordered pair its path length and the best product of shares along a shortest path; level 1 is the share itself.

    share holds both orders (or directed pairs). form linear grows paths by one predicate; split joins every two lengths that add up.
    """
    one = settle(share.select("p1", "p2", F.lit(1).alias("l"), F.col("share").alias("chain")).where(F.col("chain") > min_score))
    known, front, level = one, one, 1
    while max_level is None or level < max_level:
        level += 1
        if form == "split":
            halves = [(a, level - a) for a in range(1, level)]
            found = None
            for a, b in halves:
                x = known.where(F.col("l") == a).select("p1", F.col("p2").alias("m"), F.col("chain").alias("x")).join(known.where(F.col("l") == b).select(F.col("p1").alias("m"), "p2", F.col("chain").alias("y")), "m")
                found = x if found is None else found.unionByName(x)
        else:
            found = front.select("p1", F.col("p2").alias("m"), F.col("chain").alias("x")).join(small(one.select(F.col("p1").alias("m"), "p2", F.col("chain").alias("y"))), "m")
        best = found.where("p1 <> p2").groupBy("p1", "p2").agg(F.max(F.col("x") * F.col("y")).alias("chain")).where(F.col("chain") > min_score)
        front = settle(best.join(known.select("p1", "p2"), ["p1", "p2"], "left_anti").select("p1", "p2", F.lit(level).alias("l"), "chain"))
        if front.isEmpty():
            break
        known = known.unionByName(front)
    return known


def path_levels(share: DataFrame, max_level: int | None = None) -> DataFrame:
    """(p1, p2, l): 0 for a predicate itself, 1 if a concept is shared, else the concepts on a shortest path; no row if unreachable."""
    found = chain_scores(share, max_level).select("p1", "p2", "l")
    selves = found.select("p1").distinct().select("p1", F.col("p1").alias("p2"), F.lit(0).alias("l"))
    return found.unionByName(selves)


def best_path(share: DataFrame) -> DataFrame:
    """(p1, p2, chain): best product over all paths; pairs that share a concept keep their share. Doubles path lengths until nothing grows."""
    first = settle(share.select("p1", "p2", F.col("share").alias("chain")))
    now, state = first, None
    while True:
        two = now.select("p1", F.col("p2").alias("m"), F.col("chain").alias("x")).join(now.select(F.col("p1").alias("m"), "p2", F.col("chain").alias("y")), "m").where("p1 <> p2")
        now = settle(now.unionByName(two.select("p1", "p2", (F.col("x") * F.col("y")).alias("chain"))).groupBy("p1", "p2").agg(F.max("chain").alias("chain")))
        sums = tuple(now.agg(F.count("*"), F.round(F.sum("chain"), 9)).first())
        if sums == state:
            break
        state = sums
    kept = first.select("p1", "p2", F.col("chain").alias("own"))
    return now.join(kept, ["p1", "p2"], "left").select("p1", "p2", F.coalesce("own", "chain").alias("chain"))


def chain_local(share: DataFrame) -> DataFrame:
    """chain_scores for at most 4,096 predicates, as products of dense rows in one task."""
    preds = share.select("p1").distinct()
    if preds.limit(4097).count() > 4096:
        raise ValueError("too many predicates for the local engine")

    def run(batches):  # noqa: ANN001, ANN202
        rows = pd.concat(list(batches), ignore_index=True)
        if not len(rows):
            return
        names = sorted(set(rows["p1"]) | set(rows["p2"]))
        at = {p: i for i, p in enumerate(names)}
        one = np.zeros((len(names),) * 2)
        one[rows["p1"].map(at), rows["p2"].map(at)] = rows["share"]
        known, front, level = (one > 0) | np.eye(len(names), dtype=bool), one, 1
        while (front > 0).any():
            i, j = np.nonzero(front)
            yield pd.DataFrame({"p1": [names[k] for k in i], "p2": [names[k] for k in j], "l": np.full(len(i), level, np.int32), "chain": front[i, j]})
            grown = np.stack([(front[r][:, None] * one).max(axis=0) for r in range(len(names))])
            front, level = np.where(known, 0, grown), level + 1
            known = known | (front > 0)

    return share.select("p1", "p2", "share").coalesce(1).mapInPandas(run, "p1 string, p2 string, l int, chain double")


def levels_sql(share: DataFrame, depth: int = 3) -> DataFrame:
    """path_levels up to a depth as one recursive query; walks multiply, so for small graphs only."""
    name = f"share_{abs(hash(share)) % 10**9}"
    share.createOrReplaceTempView(name)
    return share.sparkSession.sql(
        f"""WITH RECURSIVE walk(p1, p2, l) AS (
          SELECT p1, p2, 1 FROM {name}
          UNION ALL SELECT w.p1, s.p2, w.l + 1 FROM walk w JOIN {name} s ON w.p2 = s.p1 WHERE w.l < {depth} AND w.p1 <> s.p2)
        SELECT p1, p2, CAST(min(l) AS INT) AS l FROM walk GROUP BY p1, p2"""
    )


def similarity_matrix(chain: DataFrame, preds: DataFrame) -> DataFrame:
    """(p1, p2, l, kind, sm), sparse: 1 on the diagonal, shares at level 1, chains beyond."""
    rest = chain.select("p1", "p2", "l", F.when(F.col("l") == 1, "share").otherwise("chain").alias("kind"), F.col("chain").alias("sm"))
    return preds.select(F.col("p").alias("p1"), F.col("p").alias("p2"), F.lit(0).alias("l"), F.lit("self").alias("kind"), F.lit(1.0).alias("sm")).unionByName(rest)


def row_features(sm: DataFrame, preds: DataFrame, cols: list[str] | None = None) -> DataFrame:
    """(p, features): rows of the matrix over sorted columns, 0 where absent. Cells are joined, so a row costs as much as it has columns."""
    each = preds.select("p").distinct()
    names = each.agg(F.array_sort(F.collect_list("p")).alias("names")) if cols is None else each.limit(1).select(F.array(*[F.lit(c) for c in cols]).alias("names"))
    cells = each.crossJoin(F.broadcast(names)).select(F.col("p").alias("p1"), F.posexplode("names").alias("at", "p2"))
    met = cells.join(sm.select("p1", "p2", "sm"), ["p1", "p2"], "left").select("p1", F.struct("at", F.coalesce("sm", F.lit(0.0)).alias("x")).alias("cell"))
    return met.groupBy(F.col("p1").alias("p")).agg(F.transform(F.array_sort(F.collect_list("cell")), lambda c: c["x"]).alias("features"))


def dissimilarity(sm: DataFrame, preds: DataFrame, kind: str = "one_minus", eps: float = 1e-3) -> DataFrame:
    """(p1, p2, d) of all ordered pairs of different predicates: one_minus, reciprocal, row_euclid or row_sqeuclid."""
    a, b = preds.select(F.col("p").alias("p1")).distinct(), preds.select(F.col("p").alias("p2")).distinct()
    pairs = a.crossJoin(F.broadcast(b)).where("p1 <> p2")
    if kind in ("one_minus", "reciprocal"):
        s = F.coalesce("sm", F.lit(0.0))
        d = 1 - s if kind == "one_minus" else 1 / F.greatest(s, F.lit(eps)) - 1
        return pairs.join(sm.select("p1", "p2", "sm"), ["p1", "p2"], "left").select("p1", "p2", d.alias("d"))
    # |x - y|^2 = |x|^2 + |y|^2 - 2 x.y, from sparse rows
    norm = sm.groupBy(F.col("p1").alias("p")).agg(F.sum(F.col("sm") * F.col("sm")).alias("n"))
    dot = sm.select("p1", F.col("p2").alias("c"), F.col("sm").alias("x")).join(sm.select(F.col("p1").alias("p2"), F.col("p2").alias("c"), F.col("sm").alias("y")), "c").groupBy("p1", "p2").agg(F.sum(F.col("x") * F.col("y")).alias("xy"))
    full = pairs.join(dot, ["p1", "p2"], "left").join(norm.select(F.col("p").alias("p1"), F.col("n").alias("n1")), "p1").join(norm.select(F.col("p").alias("p2"), F.col("n").alias("n2")), "p2")
    square = F.greatest(F.col("n1") + F.col("n2") - 2 * F.coalesce("xy", F.lit(0.0)), F.lit(0.0))
    return full.select("p1", "p2", (square if kind == "row_sqeuclid" else F.sqrt(square)).alias("d"))


def neighbours(sm: DataFrame, beta: float = 0.2, k: int | None = None, p: str | None = None) -> DataFrame:
    """(p1, rank, p2, sm): neighbours with more than beta, most similar first, ties by name."""
    rows = sm.where((F.col("p1") != F.col("p2")) & (F.col("sm") > beta))
    rows = rows.where(F.col("p1") == p) if p else rows
    out = rows.withColumn("rank", F.row_number().over(W.partitionBy("p1").orderBy(F.desc("sm"), "p2"))).select("p1", "rank", "p2", "sm")
    return out.where(F.col("rank") <= k) if k else out


def concept_similarity(nbr: DataFrame) -> DataFrame:
    """Share scores with predicates and concepts exchanged: (c1, c2, n1, n2, n12, share)."""
    s = share_scores(nbr.select(F.col("concept").alias("p"), F.col("p").alias("concept")))
    return s.withColumnsRenamed({"p1": "c1", "p2": "c2"})


def sm_profile(sm: DataFrame) -> DataFrame:
    """(l, n, mean, least, most): the matrix by path length."""
    return sm.groupBy("l").agg(F.count("*").alias("n"), F.avg("sm").alias("mean"), F.min("sm").alias("least"), F.max("sm").alias("most"))
