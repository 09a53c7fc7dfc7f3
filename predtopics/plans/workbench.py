"""A session over topics: list them, look at a topic's questions, make and edit a query, run it, show its graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import graph, similarity, tree
from ..operators.ontology import neighbourhood
from . import patterns, questions, sparql, weaver


class Workbench:
    """Schema-level rows (topics, walks) are small and come to the driver; facts stay where they are."""

    def __init__(self, facts: DataFrame, edges: DataFrame, members: DataFrame | None = None, alpha: float = 0.5) -> None:
        self.facts, self.edges = facts, edges
        self.deg = graph.predicate_degree(edges)
        share = similarity.share_scores(neighbourhood(edges), symmetric=True)
        preds = edges.select("p").distinct()
        self.sm = similarity.similarity_matrix(similarity.chain_scores(share), preds)
        if members is None:
            made = tree.topic_tree(preds, similarity.row_features(self.sm, preds), alpha=alpha)
            members = tree.leaves(made)
        self.members = members
        self.query: patterns.QueryGraph | None = None

    def topics(self) -> DataFrame:
        """(topic, label, n): step one."""
        size = self.members.groupBy("topic").agg(F.count("*").alias("n"))
        return tree.topic_labels(self.members, self.deg).join(size, "topic")

    def all_queries(self, n: int = 10, beta: float = 0.2, max_preds: int = 4) -> dict[str, list[patterns.QueryGraph]]:
        """What ``queries`` gives for each topic, by three jobs for all of them; walks and graphs are schema-level."""
        walks: dict[tuple[str, str], list[tuple[int, str]]] = {}
        for r in weaver.weave_all(self.members, self.sm, self.deg, n, (beta,), max_preds).collect():
            walks.setdefault((r["topic"], r["seed"]), []).append((r["step"], r["p"]))
        rows: dict[str, list[tuple]] = {}
        for r in weaver.topic_graph(self.edges, self.members).collect():
            rows.setdefault(r["topic"], []).append((r["sc"], r["p"], r["oc"]))
        made: dict[str, list[patterns.QueryGraph]] = {}
        for r in weaver.seeds(self.members, self.deg, n).orderBy("topic", "rank").collect():
            if (r["topic"], r["p"]) in walks:
                made.setdefault(r["topic"], []).append(weaver.to_query_graph([p for _, p in sorted(walks[r["topic"], r["p"]])], rows[r["topic"]]))
        return made

    def queries(self, topic: str, n: int = 10, beta: float = 0.2, max_preds: int = 4) -> list[patterns.QueryGraph]:
        """Query graphs of a topic's n best seeds: step two."""
        mine = self.members.where(F.col("topic") == topic)
        walks: dict[str, list[tuple[int, str]]] = {}
        for r in weaver.weave_all(mine, self.sm, self.deg, n, (beta,), max_preds).collect():
            walks.setdefault(r["seed"], []).append((r["step"], r["p"]))
        rows = [tuple(r) for r in weaver.topic_graph(self.edges, mine).select("sc", "p", "oc").collect()]
        order = [r["p"] for r in weaver.seeds(mine, self.deg, n).orderBy("rank").collect()]
        return [weaver.to_query_graph([p for _, p in sorted(walks[s])], rows) for s in order if s in walks]

    def questions(self, topic: str, n: int = 10, beta: float = 0.2) -> list[str]:
        return [questions.to_question(q) for q in self.queries(topic, n, beta)]

    def choose(self, q: patterns.QueryGraph | str) -> str:
        """Take a query (or its text) as the current one; its text: step three."""
        self.query = sparql.parse_sparql(q) if isinstance(q, str) else q
        return sparql.to_sparql(self.query)

    def add(self, q: patterns.QueryGraph) -> str:
        """Add another query to the current one: step four."""
        return self.choose(weaver.add_query(self.query, q) if self.query else q)

    def run(self, limit: int | None = None, allow_cross: bool = False) -> DataFrame:
        """Answers of the current query: step five."""
        sizes = {r["p"]: r["n"] for r in graph.term_frequency(self.edges).select("p", "n").collect()}
        q = patterns.order_patterns(patterns.prune_optional(self.query), sizes)
        out = patterns.evaluate(self.facts, q, allow_cross=allow_cross)
        return out.limit(limit) if limit is not None else out

    def graph(self) -> tuple[DataFrame, DataFrame]:
        """Nodes and links, with those of the current query lit: step six."""
        return weaver.graph_export(self.edges, self.query)
