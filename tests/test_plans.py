"""Patterns, text and questions."""

import pytest

from predtopics.plans import patterns, questions, sparql, weaver
from predtopics.plans.patterns import Filter, Pattern, QueryGraph

Q = QueryGraph(("?a", "?b", "?c"), (Pattern("?a", "likes", "?b"), Pattern("?a", "age", "3"), Pattern("?b", "name", "?c", 1)), (("?a", "Person"),), (Filter("?a", "!=", "?b"),), True, ("-?b", "?a"), 5)


@pytest.fixture(scope="module")
def facts(spark):
    rows = [("x", "likes", "y"), ("x", "likes", "x"), ("y", "likes", "x"), ("y", "name", "Why"), ("x", "age", "3"), ("y", "age", "4"), ("z", "likes", "y"), ("z", "age", "3")]
    return spark.createDataFrame([(s, p, o, "Person") for s, p, o in rows], "s string, p string, o string, s_class string")


def test_text_goes_both_ways():
    assert sparql.parse_sparql(sparql.to_sparql(Q)) == Q
    count = QueryGraph((), (Pattern("?a", "p", 'q"\\x'),), count="n", distinct=False)
    assert sparql.parse_sparql(sparql.to_sparql(count)) == count


def test_parser_reads_lists_and_comments():
    q = sparql.parse_sparql('PREFIX p: <http://example.org/>\nselect * where { # all\n ?a a p:Person ; p:likes ?b , ?c . optional { ?b p:name ?n } filter (?b != ?c) } order by ?a limit 3')
    assert q.patterns == (Pattern("?a", "likes", "?b"), Pattern("?a", "likes", "?c"), Pattern("?b", "name", "?n", 1)) and q.types == (("?a", "Person"),)
    assert q.limit == 3 and q.select == ("?a", "?b", "?c", "?n")
    for bad in ("SELECT ?a { ?a p:x ?b", "SELECT ?a WHERE { FILTER (?a ~ 3) }", "ASK {}"):
        with pytest.raises(ValueError):
            sparql.parse_sparql(bad)


def test_evaluation(facts):
    got = {tuple(r) for r in patterns.evaluate(facts, Q).collect()}
    assert got == {("x", "y", "Why"), ("z", "y", "Why")}
    left = QueryGraph(("?b", "?c"), (Pattern("?a", "likes", "?b"), Pattern("?b", "name", "?c", 1)))
    assert {tuple(r) for r in patterns.evaluate(facts, left).collect()} == {("y", "Why"), ("x", None)}
    assert patterns.evaluate(facts, QueryGraph(("?a",), (Pattern("?a", "likes", "?a"),))).collect()[0].a == "x"
    assert patterns.evaluate(facts, QueryGraph((), (Pattern("?a", "likes", "?b"),), count="n")).first()["n"] == 4
    assert {r.a for r in patterns.evaluate(facts, QueryGraph(("?a",), (Pattern("?a", "age", "?n"),), (), (Filter("?n", "<", "4"),))).collect()} == {"x", "z"}


def test_products_are_asked_for(facts):
    q = QueryGraph(("?a", "?c"), (Pattern("?a", "age", "?b"), Pattern("?c", "name", "?d")))
    with pytest.raises(ValueError):
        patterns.evaluate(facts, q)
    assert patterns.evaluate(facts, q, allow_cross=True).count() == 3


def test_rewrites_keep_answers(facts):
    q = weaver.pairwise(QueryGraph(("?a", "?b"), (Pattern("?a", "likes", "?b"),), (("?a", "Person"),)), "?a", strict=False)
    pruned = patterns.prune_optional(q)
    assert len(pruned.patterns) < len(q.patterns)
    assert sorted(patterns.evaluate(facts, q, allow_cross=True).collect()) == sorted(patterns.evaluate(facts, pruned, allow_cross=True).collect())
    ordered = patterns.order_patterns(Q, {"likes": 4, "age": 3, "name": 1})
    assert [p.p for p in ordered.patterns] == ["age", "likes", "name"]
    assert sorted(patterns.evaluate(facts, ordered).collect()) == sorted(patterns.evaluate(facts, Q).collect())
    strict = weaver.pairwise(QueryGraph(("?a", "?b"), (Pattern("?a", "likes", "?b"),)), "?a")
    assert {tuple(r) for r in patterns.evaluate(facts, strict).collect()} == {("x", "y", "z"), ("z", "y", "x"), ("y", "x", "x"), ("x", "x", "y")}
    with pytest.raises(ValueError):
        patterns.evaluate(facts, QueryGraph(("?a",), (Pattern("?a", "age", "?n"), Pattern("?a", "name", "?m", 1), Pattern("?k", "name", "?m", 2))))


def test_questions_and_editing():
    q = QueryGraph(("?drug", "?t"), (Pattern("?drug", "target", "?t"), Pattern("?drug", "enzyme", "?e"), Pattern("?drug", "carrierOf", "?c")), (("?drug", "Drug"),))
    assert questions.to_question(q) == "what are the target, enzyme and carrier of of a drug?"
    assert questions.to_question(weaver.drop_pattern(weaver.drop_pattern(q, "enzyme"), "carrierOf")) == "what is the target of a drug?"
    assert weaver.drop_pattern(q, "target").select == ("?drug",)
    assert weaver.add_query(q, q) == q
    assert len(weaver.decorate(q, labels={"?drug": "name"}).patterns) == 4


def test_query_graph_shares_variables():
    q = weaver.to_query_graph(["customer", "nation"], [("Order", "customer", "Customer"), ("Customer", "nation", "Nation"), ("Supplier", "nation", "Nation")])
    assert q.patterns == (Pattern("?order", "customer", "?customer"), Pattern("?customer", "nation", "?nation"))
    assert not patterns.crosses(q)
