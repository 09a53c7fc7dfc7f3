"""Queries that must act on every row of their tables, against brute force."""

import numpy as np

from predtopics import queries as own


def vectors(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").orderBy("vec_id").collect()
    return np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], np.float64), np.array([r.label for r in rows])


def test_link_terms_links_every_row(spark, sf_dir):
    ids, x, _ = vectors(spark, sf_dir)
    d = np.sqrt(((x[:, None, :] - x[None, :, :]) ** 2).sum(axis=2))
    got = {(r.id1, r.id2) for r in own.QUERIES["link_terms"](spark, sf_dir).collect()}
    assert np.abs(d - 0.9).min() > 1e-9
    assert got == {(int(ids[i]), int(ids[j])) for i, j in np.argwhere(d <= 0.9)}
    assert {a for a, _ in got} == set(ids.tolist())


def test_vector_cosine_measures_every_pair_of_a_label(spark, sf_dir):
    ids, x, label = vectors(spark, sf_dir)
    u = x / np.sqrt((x * x).sum(axis=1, keepdims=True))
    cos = u @ u.T
    got = {(r.a, r.b): r.cos for r in own.QUERIES["fn_vector_cosine"](spark, sf_dir).collect()}
    want = {(int(ids[i]), int(ids[j])): cos[i, j] for i, j in np.argwhere((label[:, None] == label[None, :]) & (ids[:, None] < ids[None, :]))}
    assert got.keys() == want.keys()
    assert max(abs(got[k] - want[k]) for k in want) < 1e-5


def test_vector_nearest_gives_five_in_the_label_of_every_row(spark, sf_dir):
    ids, x, label = vectors(spark, sf_dir)
    u = x / np.sqrt((x * x).sum(axis=1, keepdims=True))
    cos = u @ u.T
    got = {(r.a, r["rank"]): r.cos for r in own.QUERIES["fn_vector_nearest"](spark, sf_dir).collect()}
    for i in range(len(ids)):
        others = np.sort(cos[i, (label == label[i]) & (ids != ids[i])])[::-1][:5]
        assert np.allclose([got.pop((int(ids[i]), k + 1)) for k in range(len(others))], others, atol=1e-5)
    assert not got


def test_width_curves_of_every_inner_node(spark, sf_dir):
    inner = {r.parent_id for r in own.QUERIES["topic_tree"](spark, sf_dir).collect() if r.parent_id}
    got = {(r.topic, r.algorithm, r.k): r for r in own.QUERIES["width_curve_nodes"](spark, sf_dir).collect()}
    whole = own.QUERIES["width_curve"](spark, sf_dir).collect()
    assert got.keys() == {(t, r.algorithm, r.k) for t in inner for r in whole}
    root = next(r.topic_id for r in own.QUERIES["topic_tree"](spark, sf_dir).collect() if r.parent_id is None)
    assert all(abs(got[root, r.algorithm, r.k].sw - r.sw) < 1e-9 and got[root, r.algorithm, r.k].clusters == r.clusters for r in whole)


def test_composites_are_of_brand_type_and_size(spark, sf_dir):
    part, line = (spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in ("part", "lineitem"))
    sold = {r.l_partkey for r in line.select("l_partkey").distinct().collect()}
    want = {f"{r.p_brand}/{r.p_type}/{r.p_size}" for r in part.collect() if r.p_partkey in sold}
    got = own.QUERIES["share_composite_theta"](spark, sf_dir).select("p1", "p2").collect()
    assert got and {p for r in got for p in r} <= want


def test_q4_forms_are_compared_over_all_parts(spark, sf_dir, monkeypatch):
    from dataclasses import replace

    from predtopics.plans import patterns
    from predtopics.plans.patterns import Filter

    part = spark.read.parquet(f"{sf_dir}/part.parquet")
    n, small = part.count(), part.where("p_size = 1").count()
    made = own.QUERIES["q4_pruned_equals_full"](spark, sf_dir)
    assert tuple(made.first()) == (n * n, n * n, 0)
    assert str(made._jdf.queryExecution().optimizedPlan()).count("LeftOuter") == 3  # optional groups are joined, not left out by the planner
    monkeypatch.setattr(patterns, "prune_optional", lambda q, f=patterns.prune_optional: replace(f(q), filters=(Filter("?size", "=", "1"),)))
    assert tuple(own.QUERIES["q4_pruned_equals_full"](spark, sf_dir).first()) == (n * n, small * n, n * n - small * n)  # a wrong pruning is told
