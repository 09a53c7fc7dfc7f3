"""The topic tree: level by level, each topic split by the k of the highest sibling width."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..settle import settle
from .kmeans import level_sweep


@dataclass
class Tree:
    topics: DataFrame  # (topic_id, parent_id, level, ordinal, k, n_pred, sw, nsw, contribution)
    members: DataFrame  # (topic_id, level, p)
    sweeps: DataFrame  # (topic, k, restart, n_clusters, inertia, nsw)


def best_restarts(sweep: DataFrame) -> DataFrame:
    """For each (topic, k) the restart of least inertia, chosen without regard to silhouettes."""
    return sweep.withColumn("__r", F.row_number().over(W.partitionBy("topic", "k").orderBy(F.round("inertia", 9), "restart"))).where("__r = 1").drop("__r")


def choose_k(sweep: DataFrame) -> DataFrame:
    """For each topic the k of the highest sibling width, the smallest among equals."""
    return sweep.withColumn("__r", F.row_number().over(W.partitionBy("topic").orderBy(F.desc(F.round("nsw", 9)), "k"))).where("__r = 1").drop("__r")


def may_split(own_sw: float | None, size: int, level: int, alpha: float, min_split: int, max_depth: int | None, rule: str) -> bool:
    """What can be told before a topic's splits are tried. split_if_wide: topics as wide as alpha (the root always) go on; stop_above: those that are narrower."""
    if size < max(min_split, 3) or (max_depth is not None and level >= max_depth):
        return False
    return own_sw is None or (own_sw < alpha if rule == "stop_above" else own_sw >= alpha)


def splits(best: dict, own_sw: float | None, size: int, level: int, alpha: float, min_split: int, max_depth: int | None, rule: str) -> bool:
    """Whether a topic takes its best split: it may split, and with split_if_wide the split is as wide as alpha."""
    if not may_split(own_sw, size, level, alpha, min_split, max_depth, rule) or best["n_clusters"] < 2:
        return False
    return rule == "stop_above" or best["nsw"] >= alpha


def topic_tree(preds: DataFrame, features: DataFrame, k_range: tuple[int, int] = (2, 16), alpha: float = 0.5, min_split: int = 10, max_depth: int | None = None, rule: str = "split_if_wide", restarts: int = 1, init: str = "spread", dissimilarity: str = "row_sqeuclid", features_of: str = "global", feature_weight: str = "none", seed: int = 7, deg: DataFrame | None = None) -> Tree:
    """The driver holds topic ids and, of each topic, the chosen split (its predicates are schema-level: at most thousands); one job a level."""
    spark = preds.sparkSession
    names = sorted(r["p"] for r in preds.select("p").distinct().collect())
    topics = [("T0_1", None, 0, 1, None, len(names), None, None, 1.0)]
    members = [("T0_1", 0, p) for p in names]
    level, queue, sweeps = 0, {"T0_1": (names, None)} if may_split(None, len(names), 0, alpha, min_split, max_depth, rule) else {}, None
    while queue:
        rows = spark.createDataFrame([(t, p) for t, (ps, _) in queue.items() for p in ps], "topic string, p string")
        sweep = settle(best_restarts(level_sweep(rows, features, tuple(range(k_range[0], k_range[1] + 1)), restarts, init, dissimilarity, features_of, feature_weight, seed, deg)))
        log = sweep.select(F.lit(level).alias("level"), "topic", "k", "restart", "n_clusters", "inertia", "nsw")
        sweeps = log if sweeps is None else sweeps.unionByName(log)
        chosen = {r["topic"]: r.asDict() for r in choose_k(sweep).collect()}
        ahead, ordinal = {}, 0
        for topic in sorted(queue, key=lambda t: int(t.split("_")[1])):
            ps, own = queue[topic]
            best = chosen.get(topic)
            if not best or not splits(best, own, len(ps), level, alpha, min_split, max_depth, rule):
                continue
            at = next(i for i, t in enumerate(topics) if t[0] == topic)
            topics[at] = (*topics[at][:4], best["n_clusters"], *topics[at][5:7], best["nsw"], topics[at][8])
            groups: dict[int, list] = {}
            for p, c, sw in zip(best["ps"], best["labels"], best["sws"]):
                groups.setdefault(c, []).append((p, sw))
            for part in sorted(groups.values(), key=lambda g: min(p for p, _ in g)):
                ordinal += 1
                name, width = f"T{level + 1}_{ordinal}", sum(sw for _, sw in part) / len(part)
                topics.append((name, topic, level + 1, ordinal, None, len(part), width, None, len(part) / len(ps)))
                members += [(name, level + 1, p) for p, _ in part]
                ahead[name] = ([p for p, _ in part], width)
        queue = {t: v for t, v in ahead.items() if may_split(v[1], len(v[0]), level + 1, alpha, min_split, max_depth, rule)}
        level += 1
    schema = "topic_id string, parent_id string, level int, ordinal int, k int, n_pred int, sw double, nsw double, contribution double"
    if sweeps is None:
        sweeps = spark.createDataFrame([], "level int, topic string, k int, restart int, n_clusters int, inertia double, nsw double")
    return Tree(spark.createDataFrame(topics, schema), spark.createDataFrame(members, "topic_id string, level int, p string"), sweeps)


def leaves(tree: Tree) -> DataFrame:
    """(topic, p) of the topics that are not split."""
    parents = tree.topics.where("parent_id is not null").select(F.col("parent_id").alias("topic_id")).distinct()
    return tree.members.join(parents, "topic_id", "left_anti").select(F.col("topic_id").alias("topic"), "p")


def inner_nodes(tree: Tree) -> DataFrame:
    """(topic, p) of the topics that are split, the root among them."""
    parents = tree.topics.where("parent_id is not null").select(F.col("parent_id").alias("topic_id")).distinct()
    return tree.members.join(parents, "topic_id", "left_semi").select(F.col("topic_id").alias("topic"), "p")


def tree_shape(topics: DataFrame) -> DataFrame:
    """(level, topics, frontier, predicates): topics made at a level, and with the unsplit ones of the levels above."""
    parents = topics.where("parent_id is not null").select(F.col("parent_id").alias("topic_id")).distinct()
    leaf = topics.join(parents, "topic_id", "left_anti").select("level", "topic_id")
    made = topics.groupBy("level").agg(F.count("*").alias("topics"), F.sum("n_pred").alias("predicates"))
    ended = leaf.groupBy(F.col("level").alias("l")).agg(F.count("*").alias("ended"))
    carried = made.join(ended, F.col("l") < F.col("level"), "left").groupBy("level", "topics", "predicates").agg(F.coalesce(F.sum("ended"), F.lit(0)).alias("carried"))
    return carried.select("level", "topics", (F.col("topics") + F.col("carried")).alias("frontier"), "predicates")


def contribution(sizes: DataFrame) -> DataFrame:
    """(parent, topic, n) -> with rate: a topic's share of its parent."""
    return sizes.withColumn("rate", F.col("n") / F.sum("n").over(W.partitionBy("parent")))


def topic_labels(members: DataFrame, deg: DataFrame, n: int = 2) -> DataFrame:
    """(topic, label): the n predicates of highest degree."""
    ranked = members.join(deg.select("p", "io"), "p").withColumn("r", F.row_number().over(W.partitionBy("topic").orderBy(F.desc("io"), "p"))).where(F.col("r") <= n)
    return ranked.groupBy("topic").agg(F.concat_ws(" & ", F.transform(F.array_sort(F.collect_list(F.struct("r", "p"))), lambda x: x["p"])).alias("label"))


def topic_concepts(edges: DataFrame, members: DataFrame) -> DataFrame:
    """(topic, concept): concepts that a topic's predicates touch."""
    nbr = edges.select("p", F.explode(F.array("sc", "oc")).alias("concept")).distinct()
    return members.select("topic", "p").join(nbr, "p").select("topic", "concept").distinct()


def duplicate_concepts(concepts: DataFrame) -> DataFrame:
    """(concept, freq, topics) of concepts in two topics or more."""
    rows = concepts.groupBy("concept").agg(F.count("*").alias("freq"), F.concat_ws(",", F.array_sort(F.collect_set("topic"))).alias("topics"))
    return rows.where("freq > 1")


def topic_overlap(concepts: DataFrame) -> DataFrame:
    """(t1, t2, n): concepts that two topics share."""
    a, b = concepts.select(F.col("topic").alias("t1"), "concept"), concepts.select(F.col("topic").alias("t2"), "concept")
    return a.join(b, "concept").where("t1 < t2").groupBy("t1", "t2").agg(F.count("*").alias("n"))
