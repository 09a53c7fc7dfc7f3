"""Published arithmetic and hand-made graphs."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from predtopics.operators import baselines, graph, kmeans, local, normalise, ranking, similarity, sketches, tree
from predtopics.operators import silhouette as sil
from predtopics.operators.ontology import UNIVERSAL, induce_schema, neighbourhood

SHARE3 = [("A", "p1", "B"), ("A", "p2", "B"), ("A", "p3", "C"), ("D", "p4", "B"), ("E", "p5", "F")]
CHAIN5 = [("A", "p1", "B"), ("A", "p2", "B"), ("B", "p3", "C"), ("C", "p4", "D"), ("D", "p5", "E")]


def edges(spark, rows):
    return spark.createDataFrame([(*r, "x", 1) for r in rows], "sc string, p string, oc string, ns string, n_facts long")


def shares(spark, rows):
    return similarity.share_scores(neighbourhood(edges(spark, rows)), symmetric=True)


def as_dict(df, value):
    return {(r.p1, r.p2): r[value] for r in df.collect()}


@pytest.mark.parametrize("widths,want", [([(0.89, 20), (0.71, 43)], 0.77), ([(0.52, 4), (0.70, 6), (0.59, 3), (0.92, 4), (0.38, 3)], 0.64), ([(0.76, 35), (0.66, 8)], 0.74), ([(0.77, 20), (0.65, 15)], 0.72)])
def test_sibling_widths(spark, widths, want):
    rows = spark.createDataFrame([("t", str(i), sw, n) for i, (sw, n) in enumerate(widths)], "parent string, topic string, sw double, n long")
    assert round(sil.sibling_width(rows).first()["nsw"], 2) == want


@pytest.mark.parametrize("e,c,p,simple,printed", [(519, 93, 63, 0.0429, 0.00117), (72, 12, 6, 0.4706, 0.1455), (31, 7, 3, 0.6889, 0.5167), (150, 34, 3, 0.2252, 0.1229)])
def test_densities(spark, e, c, p, simple, printed):
    got = spark.range(1).select(graph._density(F.lit(e), F.lit(c), F.lit(p), "simple").alias("s"), graph._density(F.lit(e), F.lit(c), F.lit(p), "printed").alias("q")).first()
    assert got.s == pytest.approx(simple, abs=6e-5) and got.q == pytest.approx(printed, abs=6e-5)


def test_density_without_value(spark):
    assert graph.density(edges(spark, [("A", "p", "A")]), "printed").first()["density"] is None


def test_shares_of_the_hand_made_graph(spark):
    got = as_dict(shares(spark, SHARE3), "share")
    assert got["p1", "p2"] == 1 and got["p1", "p3"] == got["p1", "p4"] == 0.25 and ("p1", "p5") not in got
    kinds = {(r.p1, r.p2, r.kind): r.n_shared for r in graph.share_patterns(edges(spark, SHARE3)).collect()}
    assert kinds["p1", "p2", "subject"] == kinds["p1", "p2", "object"] == 1 and kinds["p1", "p3", "subject"] == 1 and ("p1", "p3", "object") not in kinds


def test_chains_of_the_hand_made_graph(spark):
    share = shares(spark, CHAIN5)
    want = {("p1", "p2"): (1, 1), ("p1", "p3"): (1, 1 / 4), ("p1", "p4"): (2, 1 / 16), ("p1", "p5"): (3, 1 / 64)}
    for form in ("linear", "split"):
        got = {(r.p1, r.p2): (r.l, r.chain) for r in similarity.chain_scores(share, form=form).collect()}
        assert {k: got[k] for k in want} == want
    local_ = {(r.p1, r.p2): (r.l, r.chain) for r in similarity.chain_local(share).collect()}
    assert {k: local_[k] for k in want} == want
    levels = as_dict(similarity.path_levels(share), "l")
    assert levels["p1", "p1"] == 0 and levels["p1", "p5"] == 3


def test_detour_separates_shortest_from_best(spark):
    share = spark.createDataFrame([(a, b, v) for x, y, v in [("a", "m", 0.1), ("m", "z", 0.1), ("a", "k", 0.9), ("k", "l", 0.9), ("l", "z", 0.9)] for a, b in ((x, y), (y, x))], "p1 string, p2 string, share double")
    assert as_dict(similarity.chain_scores(share), "chain")["a", "z"] == pytest.approx(0.01)
    assert as_dict(similarity.best_path(share), "chain")["a", "z"] == pytest.approx(0.729)


def test_direction(spark):
    rows = [("A", "p1", "B"), ("C", "p2", "B")]
    e = edges(spark, rows)
    assert as_dict(shares(spark, rows), "share")["p1", "p2"] == 0.25
    assert similarity.forward_pairs(e, shares(spark, rows)).count() == 0
    assert graph.connection_patterns(edges(spark, CHAIN5), 2).where("p1 = 'p1'").select("p2").distinct().collect()[0].p2 == "p4"


def test_hub_and_loop(spark):
    facts = spark.createDataFrame([("a", p, "b", "A", None, "B", None, "x") for p in ("p1", "p2", "p3")], "s string, p string, o string, s_class string, s_sub string, o_class string, o_sub string, ns string")
    rooted = induce_schema(facts, include_root=True)
    assert {r.l for r in similarity.path_levels(similarity.share_scores(neighbourhood(rooted), symmetric=True)).collect()} == {0, 1}
    assert UNIVERSAL in {r.sc for r in rooted.collect()}
    deg = graph.predicate_degree(edges(spark, [("A", "p1", "A")])).first()
    assert (deg.in_deg, deg.out_deg, deg.io) == (1, 1, 2)


def test_invariants(spark):
    rng = np.random.default_rng(3)
    rows = [(f"c{a}", f"p{p}", f"c{b}") for p, a, b in rng.integers(0, 14, (40, 3))]
    nbr = neighbourhood(edges(spark, rows))
    share = similarity.share_scores(nbr, symmetric=True)
    chain = similarity.chain_scores(share)
    sm = as_dict(similarity.similarity_matrix(chain, nbr.select("p").distinct()), "sm")
    assert all(sm[a, b] == pytest.approx(sm[b, a]) and 0 <= sm[a, b] <= 1 for a, b in sm) and all(sm[a, b] == 1 for a, b in sm if a == b)
    best = as_dict(similarity.best_path(share), "chain")
    assert all(best[k] >= v - 1e-12 for k, v in as_dict(chain, "chain").items())
    cosine = {(r.p1, r.p2): (r.share, r.cosine) for r in similarity.overlap_scores(nbr).collect()}
    assert all(s == pytest.approx(c * c) for s, c in cosine.values())
    for kw in ({"method": "collect"}, {"salt": 3}):
        assert as_dict(similarity.share_scores(nbr, **kw), "share") == as_dict(similarity.share_scores(nbr), "share")
    level = as_dict(similarity.path_levels(share), "l")
    assert all(level[a, c] <= level[a, b] + level[b, c] for (a, b), (b2, c) in itertools.product(level, level) if b == b2 and (a, c) in level)
    assert as_dict(sketches.share_scores_theta(nbr), "share").keys() == as_dict(similarity.share_scores(nbr), "share").keys()
    io = graph.predicate_degree(edges(spark, rows)).agg(F.sum("io")).first()[0]
    assert io == graph.concept_degree(edges(spark, rows)).agg(F.sum("io")).first()[0]


def test_silhouette_forms_and_conventions(spark):
    rng = np.random.default_rng(0)
    names = [f"p{i}" for i in range(9)]
    d = rng.random((9, 9))
    d = (d + d.T) / 2
    np.fill_diagonal(d, 0)
    labels = np.array([0, 0, 0, 1, 1, 2, 2, 2, 3])
    dis = spark.createDataFrame([(names[i], names[j], float(d[i, j])) for i in range(9) for j in range(9) if i != j], "p1 string, p2 string, d double")
    assign = spark.createDataFrame([(n, int(c), "t") for n, c in zip(names, labels)], "p string, cluster int, parent string")
    want = dict(zip(names, local.silhouette(d, labels)))
    for form in ("ratio", "cases"):
        got = {r.p: r.sw for r in sil.silhouette(dis, assign, form).collect()}
        assert got == pytest.approx(want) and got["p8"] == 0
    assert set(local.silhouette(d, np.zeros(9))) == {0}


def test_walk_keeps_what_is_above_beta():
    from predtopics.plans.weaver import walk

    assert [w[1] for w in walk([("s", "a", 0.5), ("s", "b", 0.1)], "s", 0.2)] == ["s", "a"]
    assert [w[1] for w in walk([("s", "a", 0.2)], "s", 0.2)] == ["s"]


def test_clusterers_against_all_partitions():
    rng = np.random.default_rng(1)
    x = rng.random((8, 2))
    d = np.sqrt(local.sq_distances(x, x))
    best = min(d[:, list(m)].min(1).sum() for m in itertools.combinations(range(8), 3))
    assert local.medoids(d, 3)[1] <= best * 1.1 and local.medoids(d, 8)[1] == pytest.approx(0, abs=1e-6)
    costs = [local.lloyd(x, 3, "random", seed)[1] for seed in range(30)]
    exact = min(sum(((x[np.array(g)] - x[np.array(g)].mean(0)) ** 2).sum() for g in part) for part in partitions(list(range(8)), 3))
    assert min(costs) == pytest.approx(exact)
    merges = local.agglomerate(d, "single")
    heights = sorted(h for _, _, h in merges)
    assert heights == pytest.approx(sorted(kruskal(d)))
    assert len(np.unique(local.divide(d, 4))) == 4 and len(np.unique(local.cut(merges, 8, 3))) == 3
    assert local.adjusted_rand(np.array([0, 0, 1, 1]), np.array([5, 5, 7, 7])) == 1 and local.normalised_information(np.array([0, 1]), np.array([1, 0])) == pytest.approx(1)


def partitions(items, k):
    if len(items) < k or k == 0:
        return
    if k == 1:
        yield [items]
        return
    if len(items) == k:
        yield [[i] for i in items]
        return
    first, rest = items[0], items[1:]
    for p in partitions(rest, k - 1):
        yield [[first], *p]
    for p in partitions(rest, k):
        for i in range(len(p)):
            yield [*p[:i], [first, *p[i]], *p[i + 1 :]]


def kruskal(d):
    root, out = list(range(len(d))), []
    for w, i, j in sorted((d[i, j], i, j) for i in range(len(d)) for j in range(i)):
        while root[i] != i:
            i = root[i]
        while root[j] != j:
            j = root[j]
        if i != j:
            root[i] = j
            out.append(w)
    return out


def test_spanning_tree_by_joins(spark):
    rng = np.random.default_rng(2)
    d = rng.random((12, 12))
    d = (d + d.T) / 2
    rows = spark.createDataFrame([(f"v{i:02}", f"v{j:02}", float(d[i, j])) for i in range(12) for j in range(12) if i != j], "p1 string, p2 string, d double")
    assert sorted(r.d for r in baselines.spanning_tree(rows).collect()) == pytest.approx(sorted(kruskal(d)))


def test_relational_and_local_lloyd_agree(spark):
    rng = np.random.default_rng(4)
    x = np.vstack([rng.normal(c, 0.2, (6, 3)) for c in (0, 3, 6)])
    feats = spark.createDataFrame([(f"p{i:02}", v.tolist()) for i, v in enumerate(x)], "p string, features array<double>")
    start = spark.createDataFrame([(0, "p00"), (1, "p06"), (2, "p12")], "cluster int, p string")
    assign, centres = kmeans.lloyd(kmeans.long_rows(feats), start)
    got = [r.cluster for r in assign.orderBy("p").collect()]
    assert got == [0] * 6 + [1] * 6 + [2] * 6
    cost = sum(r.cost for r in kmeans.inertia(kmeans.long_rows(feats), assign, centres).collect())
    assert cost == pytest.approx(local.lloyd(x, 3)[1])


def test_tree_partitions_and_rules(spark):
    rng = np.random.default_rng(5)
    x = np.vstack([rng.normal(c, 0.05, (8, 6)) for c in (0, 1, 4)])
    feats = spark.createDataFrame([(f"p{i:02}", v.tolist() + [0.0] * 18) for i, v in enumerate(x)], "p string, features array<double>")
    made = tree.topic_tree(feats.select("p"), feats, (2, 5), min_split=6)
    for level in range(1, made.topics.agg(F.max("level")).first()[0] + 1):
        rows = made.members.where(F.col("level") == level)
        assert rows.count() == rows.select("p").distinct().count()
    assert tree.leaves(made).count() == 24
    rates = made.topics.where("parent_id is not null").groupBy("parent_id").agg(F.sum("contribution").alias("c")).collect()
    assert all(r.c == pytest.approx(1) for r in rates)
    good = {"n_clusters": 2, "nsw": 0.6}
    rule = lambda **k: tree.splits(k.get("best", good), k.get("own"), k.get("size", 20), k.get("level", 0), 0.5, 10, k.get("depth"), k.get("rule", "split_if_wide"))
    assert rule() and not rule(size=9) and not rule(own=0.4) and not rule(best={"n_clusters": 2, "nsw": 0.4}) and not rule(level=3, depth=3)
    assert rule(own=0.4, rule="stop_above") and not rule(own=0.6, rule="stop_above")


def test_frontier_counts_unsplit_leaves(spark):
    topics = [("r", None, 0, 63), ("a", "r", 1, 20), ("b", "r", 1, 43), *[(f"a{i}", "a", 2, 4) for i in range(5)], ("b1", "b", 2, 35), ("b2", "b", 2, 8), ("c1", "b1", 3, 20), ("c2", "b1", 3, 15)]
    shape = tree.tree_shape(spark.createDataFrame(topics, "topic_id string, parent_id string, level int, n_pred int")).orderBy("level").collect()
    assert [r.frontier for r in shape] == [1, 2, 7, 8]


def test_ranking_ties_and_missing(spark):
    rows = [("a", 5, 5, 0.5, 0.5, 0.5), ("b", 5, 5, 0.5, 0.5, 0.5), ("c", 9, 9, None, 0.9, 0.9)]
    crit = spark.createDataFrame(rows, "topic string, top_predicates int, top_concepts int, similarity double, width double, density double")
    got = {r.topic: r for r in ranking.integrated_rank(crit).collect()}
    assert got["c"].overall == 1 and got["a"].overall == 2 and got["b"].overall == 3 and got["c"].rank_similarity == 3 and got["a"].rank_width == got["b"].rank_width == 2
    assert ranking.integrated_rank(crit, missing="skip").where("topic = 'c'").first()["mean_rank"] == 1


def test_terms(spark):
    links = spark.createDataFrame([("a", "b"), ("b", "c"), ("x", "y"), *[(f"k{i}", f"k{i + 1}") for i in range(1, 9)]], "a string, b string")
    names = {r.term: r.name for r in normalise.contract_same(links).collect()}
    assert names["c"] == "a" and names["y"] == "x" and names["k9"] == "k1"
    facts = spark.createDataFrame([("c", "p", "y"), ("a", "p", "x")], "s string, p string, o string")
    assert normalise.rewrite_terms(facts, normalise.contract_same(links)).count() == 1
    pts = np.random.default_rng(0).random((60, 3))
    v = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(pts)], "id int, v array<double>")
    got = {(r.id1, r.id2) for r in normalise.link_terms(v, v, 0.3).collect()}
    assert got == {(i, j) for i in range(60) for j in range(60) if math.dist(pts[i], pts[j]) <= 0.3}
