"""Queries whose answers or pairs are too many to make one by one: the same results from counts, classes and blocks."""

import pytest

from predtopics.plans import patterns
from predtopics.plans.patterns import Pattern, QueryGraph


def kinds(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


FACTS = [("x1", "a", "t1"), ("x1", "b", "u1"), ("x2", "a", "t1"), ("x2", "b", "u1"), ("x2", "b", "u2"), ("y1", "c", "t1"), ("y2", "c", "t2"), ("z", "d", "w"), ("z", "d", "v"), ("z", "d", "v")]


@pytest.fixture(scope="module")
def facts(spark):
    return spark.createDataFrame([(*f, f[0][0].upper()) for f in FACTS], "s string, p string, o string, s_class string")


@pytest.mark.parametrize("keys", [["t"], ["t", "x"], ["u", "o"], ["t", "k"]])
def test_counted_answers_are_those_of_evaluate(facts, keys):
    q = QueryGraph(("?x", "?t", "?u", "?y", "?z", "?o", "?k"), (Pattern("?x", "a", "?t"), Pattern("?x", "b", "?u"), Pattern("?y", "c", "?t"), Pattern("?z", "d", "?o")), (("?k", "Y"),))
    want = patterns.evaluate(facts, q, allow_cross=True).groupBy(*keys).count().collect()
    got = patterns.counted(facts, q, keys).collect()
    assert want and sorted(map(tuple, got)) == sorted(map(tuple, want))


def test_counted_without_answers_is_empty_and_filters_are_refused(facts):
    q = QueryGraph(("?x", "?t", "?z"), (Pattern("?x", "a", "?t"), Pattern("?z", "none", "w")))
    assert patterns.counted(facts, q, ["t"]).count() == 0
    with pytest.raises(ValueError):
        patterns.counted(facts, QueryGraph(("?t",), q.patterns), ["t"])


def test_endpoint_query_groups_before_it_joins(spark, sf_dir):
    from predtopics import queries as own

    plan = kinds(own.QUERIES["endpoint_query"](spark, sf_dir))
    assert plan.index("Aggregate") > plan.index("Join")  # no aggregate above the product of line items


@pytest.mark.parametrize("strict", [True, False])
def test_functional_predicates_change_no_answer(spark, strict):
    from predtopics.queries import workloads as w

    rows = [("p1", "A", "t", "1"), ("p2", "A", "t", "1"), ("p3", "A", "t", "2"), ("p4", "B", None, "1"), ("p5", "B", "t", "1")]
    facts = spark.createDataFrame([(s, p, o, "Part") for s, *v in rows for p, o in zip(("brand", "type", "size"), v) if o], "s string, p string, o string, s_class string")
    q = patterns.prune_optional(w.q4_graph(strict))
    single = patterns.functional(facts, q)
    want = patterns.evaluate(facts, q, w.small_parts(facts), allow_cross=True)
    got = patterns.evaluate(facts, q, w.small_parts(facts), allow_cross=True, single=single)
    assert single == {"brand", "type", "size"} and "Aggregate [part#" in kinds(want) and want.count()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert len([x for x in kinds(got).split("\n") if "Aggregate" in x and "part2#" in x and "max(" not in x]) == (0 if strict else 1)  # no answers are compared, only the class of small parts
    twice = facts.unionByName(facts.where("s = 'p2' and p = 'brand'").withColumn("o", patterns.F.lit("B")))
    single = patterns.functional(twice, q)
    assert single == {"type", "size"}
    got = patterns.evaluate(twice, q, w.small_parts(twice), allow_cross=True, single=single).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, patterns.evaluate(twice, q, w.small_parts(twice), allow_cross=True).collect()))


def test_folded_answers_stand_for_all(spark):
    from predtopics.queries import workloads as w

    facts = spark.createDataFrame([(f"p{k}", p, o, "Part") for k in range(30) for p, o in (("brand", f"b{k % 2}"), ("type", "t"), ("size", str(k % 3)))], "s string, p string, o string, s_class string")
    for q in (w.q4_graph(False), patterns.prune_optional(w.q4_graph(False))):
        got = patterns.evaluate(facts, q, w.small_parts(facts), allow_cross=True, single=patterns.functional(facts, q), fold="?part")
        assert got.count() == 2 * 10 and got.agg(patterns.F.sum("__n")).first()[0] == 100 == patterns.evaluate(facts, q, w.small_parts(facts), allow_cross=True).count()
    with pytest.raises(ValueError):
        patterns.evaluate(facts, w.q4_graph(True), single=frozenset({"brand", "type", "size"}), fold="?part")


def test_one_stands_for_all_that_answer_alike(spark):
    from predtopics.queries import workloads as w

    F, q = patterns.F, w.q4_graph(False, whole=True)
    rows = [(f"p{k}", p, o, "Part") for k in range(40) for p, o in (("brand", f"b{k % 2}"), ("type", "t"), ("size", str(k % 3)), ("name", f"n{k}")) if (p, k) not in {("brand", 38), ("size", 39)}]
    rows += [("p3", "brand", "b0", "Part"), ("p9", "brand", "b0", "Part"), ("p4", "type", "t", "Part"), ("only", "name", "n", "Part"), ("x", "size", "1", "Other")]
    facts = spark.createDataFrame(rows, "s string, p string, o string, s_class string")
    single = patterns.functional(facts, q)
    assert single == {"size"}  # two brands of p3 and p9, and a link of p4 twice, undo nothing
    fold = {v: patterns.settle(patterns.alike(facts, q, v)) for v in ("?part", "?part2")}
    got = {v: sorted(r["__n"] for r in df.collect()) for v, df in fold.items()}
    assert got["?part2"] == [1, 1, 1, 1, 2, 4, 6, 6, 6, 7, 7]  # without brand, without size, without links and x, which is no part; two brands; others
    for form in (q, patterns.prune_optional(q)):
        want = patterns.evaluate(facts, form, allow_cross=True).count()
        some = patterns.evaluate(facts, form, allow_cross=True, single=single, fold=fold)
        assert some.agg(F.sum("__n")).first()[0] == want == 38 * 41 and some.count() == some.select("part", "part2").distinct().count() < 100
    small, types = w.q4_graph(False), w.small_parts(facts)  # classes that are told aside, of which x has one
    want = patterns.evaluate(facts, small, types, allow_cross=True).count()
    assert patterns.evaluate(facts, small, types, allow_cross=True, single=single, fold="?part2").agg(F.sum("__n")).first()[0] == want > 0
    for bad in (patterns.replace(q, limit=3), patterns.replace(q, distinct=False), patterns.replace(q, select=("?part2",))):
        with pytest.raises(ValueError):
            patterns.evaluate(facts, bad, allow_cross=True, single=single, fold="?part")


def test_sessions_do_not_come_to_the_driver(spark, sf_dir, tmp_path):
    from predtopics import queries as own
    from predtopics.streaming import events as ev

    got = own.QUERIES["stream_session"](spark, sf_dir)
    assert "LocalRelation" not in kinds(got) and "StateScan" in got._jdf.queryExecution().executedPlan().toString() + kinds(got) or "statestore" in kinds(got).lower() or "RelationV2" in kinds(got)
    spark.read.parquet(f"{sf_dir}/events.parquet").limit(0).write.parquet(str(tmp_path / "events.parquet"))
    assert ev.drain_sessions(ev.source(spark, str(tmp_path))).count() == 0
    rows = spark.sql("select * from values (1L, timestamp_ntz'2024-01-02 10:00:00', 7L), (2L, timestamp_ntz'2024-01-02 10:29:59', 7L), (3L, timestamp_ntz'2024-01-01 00:00:00', 7L) t(event_id, ts, user_id)").selectExpr("*", "'a' as event_type", "1.0D as value", "'' as props")
    for n, some in enumerate((rows.where("event_id < 3"), rows.where("event_id = 3"))):
        some.coalesce(1).write.parquet(str(tmp_path / "late" / f"{n}"))
    (tmp_path / "two" / "events.parquet").mkdir(parents=True)
    for n in range(2):
        for f in (tmp_path / "late" / str(n)).glob("*.parquet"):
            (tmp_path / "two" / "events.parquet" / f"{n}.parquet").write_bytes(f.read_bytes())
    got = ev.drain_sessions(ev.source(spark, str(tmp_path / "two"), files=1)).selectExpr("user_id", "n").collect()
    assert sorted(map(tuple, got)) == [(7, 1), (7, 2)]  # the late row is a session of its own


@pytest.fixture(scope="module")
def copies(spark):
    """Vectors with 40 copies of one, a null one, one with a null component, and a null label; blocks of 8 rows."""
    import random

    rng = random.Random(5)
    rows = [(k, [1.0, 0.5, 0.25] if k < 40 else [rng.gauss(0, 1) for _ in range(3)], k % 2) for k in range(100)]
    rows += [(100, None, 0), (101, [1.0, None, 0.0], 1), (102, [1.0, 0.0, 0.0], None)]
    return spark.createDataFrame(rows, "id long, v array<float>, label int")


def plainly(rows, a, b):
    import numpy as np

    whole = lambda v: v is not None and None not in v
    x, y = rows[a].v, rows[b].v
    if not (whole(x) and whole(y)):
        return None
    x, y = np.array(x, float), np.array(y, float)
    return float(x @ y / np.sqrt((x @ x) * (y @ y)))


def test_blocks_give_all_cosines_of_a_label(copies, monkeypatch):
    from predtopics.operators import vectors

    rows = {r.id: r for r in copies.collect()}
    monkeypatch.setattr(vectors.dealt, "__defaults__", (8,))
    made = vectors.pair_cosines(copies, "label")
    assert "aggregate(zip_with" not in kinds(made)
    got = {(r.a, r.b): r.cos for r in made.collect()}
    assert got.keys() == {(a, b) for a in rows for b in rows if a < b and rows[a].label is not None and rows[a].label == rows[b].label}
    assert all((c is None) == (plainly(rows, *k) is None) and (c is None or abs(c - plainly(rows, *k)) < 1e-5) for k, c in got.items())


def test_blocks_give_the_nearest_with_ties_to_the_smaller_id(copies, monkeypatch):
    from predtopics.operators import relational, vectors

    rows = {r.id: r for r in copies.where("label is not null").collect()}
    monkeypatch.setattr(vectors.dealt, "__defaults__", (8,))
    got = {(r.a, r["rank"]): r.b for r in relational.topk(vectors.nearest(copies, "label", 5), ["label", "a"], [patterns.F.desc("cos"), patterns.F.col("b")], 5).collect()}
    for a in rows:
        others = [b for b in rows if b != a and rows[b].label == rows[a].label]
        far = {b: -2.0 if (c := plainly(rows, a, b)) is None else round(c, 12) for b in others}
        assert [got.pop((a, k + 1)) for k in range(5)] == sorted(others, key=lambda b: (-far[b], b))[:5]
    assert not got


def test_links_of_copies_and_of_blocks_that_pivots_hold_apart(copies):
    from predtopics.operators import normalise, vectors

    whole = copies.where("id < 100")
    rows = {r.id: r.v for r in whole.collect()}
    want = {(a, b) for a in rows for b in rows if sum((x - y) ** 2 for x, y in zip(rows[a], rows[b])) ** 0.5 <= 0.5}
    assert {(r.id1, r.id2) for r in normalise.link_terms(whole, whole, 0.5).collect()} == want
    far = whole.withColumn("far", patterns.F.expr("array(sqrt(aggregate(v, 0d, (s, x) -> s + x * x)))"))
    assert {(r.id1, r.id2) for r in vectors.within(far, far, 0.5, 1, rows=8).collect()} == want
    assert normalise.link_terms(whole.limit(0), whole, 0.5).count() == 0


@pytest.mark.parametrize("lg_k", [4, 12])
def test_shares_of_sketches_are_the_sketches_own(spark, lg_k):
    from predtopics.operators import sketches

    F = patterns.F
    nbr = spark.range(6000).selectExpr("concat('p', id % 23) as p", "cast(pmod(xxhash64(id), 900) as string) as concept").unionByName(spark.sql("select 'one' as p, '5' as concept union all select 'two', '5' union all select 'two', '6' union all select 'none', null")).distinct()
    sk = nbr.groupBy("p").agg(F.theta_sketch_agg("concept", lg_k).alias("k"))
    for r in sk.selectExpr("p", "k", "theta_sketch_estimate(k) as n").collect():
        held, theta = sketches.retained(bytes(r.k))
        assert r.n == int(len(held) / (theta / sketches.WHOLE) + 0.5) and len(set(held.tolist())) == len(held) and (held < theta).all()
    a, b = sk.selectExpr("p as p1", "k as k1"), sk.selectExpr("p as p2", "k as k2")
    want = a.join(b, F.expr("p1 < p2")).selectExpr("p1", "p2", "theta_sketch_estimate(k1)", "theta_sketch_estimate(k2)", "theta_sketch_estimate(theta_intersection(k1, k2)) as n12").where("n12 > 0").collect()
    made = sketches.share_scores_theta(nbr, lg_k, rows=7)
    assert "theta_intersection" not in kinds(made)
    got = made.collect()
    assert sorted(tuple(r)[:5] for r in got) == sorted(map(tuple, want))
    assert all(r.share == r.n12 * r.n12 / (r.n1 * r.n2) for r in got)


def test_builtin_predicates_are_counted_in_the_tables(spark, sf_dir):
    import glob

    import duckdb

    from predtopics import queries as own

    con = duckdb.connect()
    for name in ("documents", "pages"):
        assert glob.glob(f"{sf_dir}/{name}.parquet")
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{sf_dir}/{name}.parquet'")
    got = own.QUERIES["builtin_predicates"](spark, sf_dir)
    assert len(got.inputFiles()) == 2
    assert sorted(map(tuple, got.collect())) == sorted(con.sql(own.ORACLES["builtin_predicates"]).fetchall())
