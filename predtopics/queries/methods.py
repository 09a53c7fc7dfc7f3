"""Methods, variants, baselines and measures over the schema graph of the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators import baselines, graph, kmeans, normalise, ontology, ranking, similarity, sketches, tree
from ..operators import silhouette as sil
from ..operators.ontology import incidence, neighbourhood, schema, schema_sql
from ..plans import weaver
from ..settle import settle
from ..sources.tables import stamp

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
_MADE: dict[tuple, object] = {}


def query(name: str, sql: str | None = None):  # noqa: ANN201
    def add(f: Callable) -> Callable:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def once(spark: SparkSession, key: tuple, make: Callable):  # noqa: ANN201
    """Schema-level results that several queries use, made once a session and state of the tables; a key begins with their folder."""
    key = (spark.sparkContext.applicationId, stamp(spark, key[0]), *key)
    if key not in _MADE:
        _MADE[key] = make()
    return _MADE[key]


def forget() -> None:
    """Drop what ``once`` and the schema hold, so that the next query makes it anew."""
    _MADE.clear()
    ontology.forget()


def edges(s: SparkSession, d: str, kind: str = "base") -> DataFrame:
    return schema(s, d, kind)


def preds(s: SparkSession, d: str, kind: str = "base") -> DataFrame:
    return edges(s, d, kind).select("p").distinct()


def share(s: SparkSession, d: str, kind: str = "base") -> DataFrame:
    return once(s, (d, kind, "share"), lambda: settle(similarity.share_scores(neighbourhood(edges(s, d, kind)), symmetric=True)))


def chain(s: SparkSession, d: str, kind: str = "base") -> DataFrame:
    return once(s, (d, kind, "chain"), lambda: settle(similarity.chain_scores(share(s, d, kind))))


def matrix(s: SparkSession, d: str, kind: str = "base") -> DataFrame:
    return once(s, (d, kind, "sm"), lambda: settle(similarity.similarity_matrix(chain(s, d, kind), preds(s, d, kind))))


def features(s: SparkSession, d: str, kind: str = "base") -> DataFrame:
    return once(s, (d, kind, "rows"), lambda: settle(similarity.row_features(matrix(s, d, kind), preds(s, d, kind))))


def fixed(s: SparkSession, d: str) -> DataFrame:
    """(topic, p): a fixed assignment, by the namespace of a predicate's first subject concept."""
    return edges(s, d).groupBy("p").agg(F.min_by("ns", "sc").alias("topic")).select("topic", "p")


def fixed_silhouette(s: SparkSession, d: str) -> DataFrame:
    assign = fixed(s, d).select("p", F.col("topic").alias("cluster"), F.lit("root").alias("parent"))
    return sil.silhouette(similarity.dissimilarity(matrix(s, d), preds(s, d)), assign)


def built_tree(s: SparkSession, d: str) -> tree.Tree:
    return once(s, (d, "tree"), lambda: tree.topic_tree(preds(s, d, "refined"), features(s, d, "refined")))


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


# SQL building blocks -------------------------------------------------------------------------------------------------

INC = "inc AS (SELECT DISTINCT p, sc AS concept, 'in' AS side FROM edges UNION SELECT DISTINCT p, oc, 'out' FROM edges)"
NBR = "nbr AS (SELECT DISTINCT p, concept FROM inc)"
SIZE = "size AS (SELECT p, count(*) AS n FROM nbr GROUP BY p)"
SHARE = "share AS (SELECT x.p1, x.p2, a.n AS n1, b.n AS n2, x.n12, x.n12 * x.n12 / CAST(a.n * b.n AS DOUBLE) AS share FROM (SELECT a.p AS p1, b.p AS p2, count(*) AS n12 FROM nbr a JOIN nbr b ON a.concept = b.concept AND a.p <> b.p GROUP BY 1, 2) x JOIN size a ON a.p = x.p1 JOIN size b ON b.p = x.p2)"
DEPTH = 8


def _levels(first: str = "SELECT p1, p2, share AS c FROM share") -> str:
    parts = [f"f1 AS MATERIALIZED ({first})", "v1 AS MATERIALIZED (SELECT p1, p2, 1 AS l, c FROM f1)"]
    for k in range(2, DEPTH + 1):
        parts.append(f"f{k} AS MATERIALIZED (SELECT a.p1, b.p2, max(a.c * b.c) AS c FROM f{k - 1} a JOIN f1 b ON a.p2 = b.p1 WHERE a.p1 <> b.p2 AND NOT EXISTS (SELECT 1 FROM v{k - 1} v WHERE v.p1 = a.p1 AND v.p2 = b.p2) GROUP BY 1, 2)")
        parts.append(f"v{k} AS MATERIALIZED (SELECT * FROM v{k - 1} UNION ALL SELECT p1, p2, {k}, c FROM f{k})")
    return ", ".join([*parts, f"chain AS (SELECT p1, p2, l, c AS chain FROM v{DEPTH})"])


SM = "sm AS MATERIALIZED (SELECT p AS p1, p AS p2, 0 AS l, 'self' AS kind, CAST(1 AS DOUBLE) AS sm FROM size UNION ALL SELECT p1, p2, l, CASE WHEN l = 1 THEN 'share' ELSE 'chain' END, chain FROM chain)"
FIXED = "fixed AS (SELECT p, arg_min(ns, sc) AS topic FROM edges GROUP BY p)"
PDEG = "pdeg AS (SELECT p, count(DISTINCT sc) AS in_deg, count(DISTINCT oc) AS out_deg, count(DISTINCT sc) + count(DISTINCT oc) AS io FROM edges GROUP BY p)"
CDEG = "cdeg AS (SELECT concept, count(*) FILTER (side = 'out') AS in_deg, count(*) FILTER (side = 'in') AS out_deg, count(*) AS io FROM inc GROUP BY concept)"
DIS = "dis AS MATERIALIZED (SELECT a.p AS p1, b.p AS p2, 1 - coalesce(sm.sm, 0) AS d FROM size a JOIN size b ON a.p <> b.p LEFT JOIN sm ON sm.p1 = a.p AND sm.p2 = b.p)"
SIL = """sil AS MATERIALIZED (SELECT x.p, x.topic AS cluster, max(m) FILTER (x.topic = y.c) AS a, min(m) FILTER (x.topic <> y.c) AS b, arg_min(y.c, {'m': m, 'c': y.c}) FILTER (x.topic <> y.c) AS sibling
 FROM fixed x LEFT JOIN (SELECT d.p1, f.topic AS c, avg(d.d) AS m FROM dis d JOIN fixed f ON f.p = d.p2 GROUP BY 1, 2) y ON y.p1 = x.p GROUP BY 1, 2),
sw AS MATERIALIZED (SELECT *, 'root' AS parent, CASE WHEN a IS NULL OR b IS NULL OR greatest(a, b) = 0 THEN 0 ELSE (b - a) / greatest(a, b) END AS sw FROM sil)"""
TC = "tc AS (SELECT DISTINCT f.topic, n.concept FROM fixed f JOIN nbr n ON n.p = f.p)"


def sql(select: str, *blocks: str, kind: str = "base") -> str:
    return "WITH " + ", ".join([f"edges AS MATERIALIZED ({schema_sql(kind)})", *blocks]) + " " + select


GRAPH = (INC, NBR, SIZE, SHARE)
CHAINS = (*GRAPH, _levels())
FULL = (*CHAINS, SM)
TOPICS = (*FULL, FIXED)
JUDGED = (*TOPICS, DIS, SIL)

# ontology and graph ---------------------------------------------------------------------------------------------------

DENSITY = "2.0 * e / nullif(CAST((c + p) AS DOUBLE) * (c + p - 1), 0)"
PRINTED = "2.0 * e / nullif(CAST((c + p) AS DOUBLE) * (c - 1) * (p - 1), 0)"
STATS = f"""SELECT feature, value FROM (SELECT * FROM (SELECT count(*) AS schema_edges, sum(n_facts) AS facts, count(DISTINCT p) AS predicates, sum(n_facts) AS domain_facts, count(DISTINCT p) AS domain_predicates, count(DISTINCT ns) AS namespaces FROM edges),
 (SELECT e AS links, c AS concepts, round({DENSITY}, 9) AS density_simple, round({PRINTED}, 9) AS density_printed FROM (SELECT count(*) AS e, count(DISTINCT concept) AS c, count(DISTINCT p) AS p FROM inc))) AS t
 UNPIVOT (value FOR feature IN (schema_edges, facts, predicates, domain_facts, domain_predicates, namespaces, links, concepts, density_simple, density_printed))"""
_cast = "SELECT CAST(schema_edges AS DOUBLE) AS schema_edges, CAST(facts AS DOUBLE) AS facts, CAST(predicates AS DOUBLE) AS predicates, CAST(domain_facts AS DOUBLE) AS domain_facts, CAST(domain_predicates AS DOUBLE) AS domain_predicates, CAST(namespaces AS DOUBLE) AS namespaces, CAST(links AS DOUBLE) AS links, CAST(concepts AS DOUBLE) AS concepts, density_simple, density_printed FROM"
STATS = STATS.replace("SELECT * FROM (SELECT count(*)", _cast + " (SELECT count(*)", 1)

for _k in ("base", "refined"):
    _n = "" if _k == "base" else "_refined"
    query(f"ontology_stats{_n}", sql(STATS, INC, kind=_k))(lambda s, d, k=_k: graph.ontology_stats(edges(s, d, k)))
    query(f"schema_edges{_n}", sql("SELECT * FROM edges", kind=_k))(lambda s, d, k=_k: edges(s, d, k))
    query(f"incidence{_n}", sql("SELECT * FROM inc", INC, kind=_k))(lambda s, d, k=_k: incidence(edges(s, d, k)))
query("schema_edges_rooted", sql("SELECT * FROM edges", kind="rooted"))(lambda s, d: edges(s, d, "rooted"))
query("namespace_table", sql("SELECT ns, count(DISTINCT sc) AS n_concepts, count(DISTINCT p) AS n_predicates FROM edges GROUP BY ns"))(lambda s, d: graph.namespace_table(edges(s, d)))
query("neighbourhood", sql("SELECT * FROM nbr", INC, NBR))(lambda s, d: neighbourhood(edges(s, d)))
query(
    "share_patterns",
    sql("""SELECT p1, p2, kind, count(*) AS n_shared FROM (SELECT p1, p2, concept, unnest(list_filter([CASE WHEN s THEN 'subject' END, CASE WHEN o THEN 'object' END, CASE WHEN s AND o THEN 'both' END, CASE WHEN x THEN 'cross' END], lambda k: k IS NOT NULL)) AS kind
    FROM (SELECT a.p AS p1, b.p AS p2, a.concept, bool_or(a.side = 'in' AND b.side = 'in') AS s, bool_or(a.side = 'out' AND b.side = 'out') AS o, bool_or(a.side <> b.side) AS x FROM inc a JOIN inc b ON a.concept = b.concept AND a.p < b.p GROUP BY 1, 2, 3)) GROUP BY 1, 2, 3""", INC),
)(lambda s, d: graph.share_patterns(edges(s, d)))
query(
    "connection_patterns_l2",
    sql("SELECT DISTINCT a.p AS p1, c.p AS p2, 2 AS level, concat_ws('>', a.p, a.oc, b.p, b.oc, c.p) AS path FROM edges a JOIN edges b ON a.oc = b.sc AND a.p <> b.p JOIN edges c ON b.oc = c.sc AND c.p <> a.p AND c.p <> b.p"),
)(lambda s, d: graph.connection_patterns(edges(s, d), 2).withColumn("path", F.concat_ws(">", "path")))
query("predicate_degree", sql("SELECT * FROM pdeg", PDEG))(lambda s, d: graph.predicate_degree(edges(s, d)))
query("concept_degree", sql("SELECT * FROM cdeg", INC, CDEG))(lambda s, d: graph.concept_degree(edges(s, d)))
query("top_predicates", sql("SELECT *, CAST(row_number() OVER (ORDER BY io DESC, p) AS INT) AS rank FROM pdeg QUALIFY rank <= 20", PDEG))(lambda s, d: graph.rank_predicates(graph.predicate_degree(edges(s, d))))
query("top_concepts", sql("SELECT *, CAST(rank() OVER (ORDER BY io DESC) AS INT) AS rank FROM cdeg QUALIFY rank <= 20", INC, CDEG))(lambda s, d: graph.rank_concepts(graph.concept_degree(edges(s, d))))
query("term_frequency", sql("SELECT p, CAST(sum(n_facts) AS BIGINT) AS n, round(sum(n_facts) / (SELECT CAST(sum(n_facts) AS DOUBLE) FROM edges), 6) AS share FROM edges GROUP BY p"))(lambda s, d: rounded(graph.term_frequency(edges(s, d))))
query("term_frequency_concepts", sql("SELECT concept, CAST(sum(n) AS BIGINT) AS n, round(sum(n) / CAST(sum(sum(n)) OVER () AS DOUBLE), 6) AS share FROM (SELECT sc AS concept, n_facts AS n FROM edges UNION ALL SELECT oc, n_facts FROM edges) GROUP BY 1"))(lambda s, d: rounded(graph.term_frequency(edges(s, d), "concept")))
for _k, _f in (("simple", DENSITY), ("printed", PRINTED)):
    query(f"density_{_k}", sql(f"SELECT e, c, p, round({_f}, 6) AS density FROM (SELECT count(*) AS e, count(DISTINCT concept) AS c, count(DISTINCT p) AS p FROM inc)", INC))(lambda s, d, k=_k: rounded(graph.density(edges(s, d), k)))
    query(f"topic_density_{_k}", sql(f"SELECT topic, e, c, p, round({_f}, 6) AS density FROM (SELECT topic, count(*) AS e, count(DISTINCT concept) AS c, count(DISTINCT inc.p) AS p FROM inc JOIN fixed ON fixed.p = inc.p GROUP BY topic)", INC, FIXED))(lambda s, d, k=_k: rounded(graph.topic_density(edges(s, d), fixed(s, d), k)))

# similarity -------------------------------------------------------------------------------------------------------------

_SH = "SELECT p1, p2, n1, n2, n12, round(share, 6) AS share FROM share WHERE p1 < p2"
query("share_scores", sql(_SH, *GRAPH))(lambda s, d: rounded(similarity.share_scores(neighbourhood(edges(s, d)))))
query("share_scores_refined", sql(_SH, *GRAPH, kind="refined"))(lambda s, d: rounded(similarity.share_scores(neighbourhood(edges(s, d, "refined")))))
query("share_scores_rooted", sql(_SH, *GRAPH, kind="rooted"))(lambda s, d: rounded(similarity.share_scores(neighbourhood(edges(s, d, "rooted")))))
query("share_collect", sql(_SH, *GRAPH))(lambda s, d: rounded(similarity.share_scores(neighbourhood(edges(s, d)), "collect")))
query("share_salted", sql(_SH, *GRAPH))(lambda s, d: rounded(similarity.share_scores(neighbourhood(edges(s, d)), salt=4)))
query("share_rational", sql("SELECT p1, p2, n1, n2, n12, n12 * n12 AS num, n1 * n2 AS den FROM share WHERE p1 < p2", *GRAPH))(lambda s, d: similarity.share_scores(neighbourhood(edges(s, d)), number="rational"))
query("share_decimal", sql(_SH.replace("round(share, 6)", "round(CAST(share AS DOUBLE), 6)"), *GRAPH))(lambda s, d: rounded(similarity.share_scores(neighbourhood(edges(s, d)), number="decimal").withColumn("share", F.col("share").cast("double"))))
_CUT = "nbr AS (SELECT p, concept FROM (SELECT DISTINCT p, concept, count(*) OVER (PARTITION BY concept) AS n FROM (SELECT DISTINCT p, concept FROM inc)) WHERE n <= 5)"
query("share_hub_cut", sql(_SH, INC, _CUT, SIZE, SHARE))(lambda s, d: rounded(similarity.share_scores(neighbourhood(edges(s, d)), max_degree=5)))
query("overlap_scores", sql("SELECT p1, p2, round(share, 6) AS share, round(n12 / CAST(n1 + n2 - n12 AS DOUBLE), 6) AS jaccard, round(2.0 * n12 / (n1 + n2), 6) AS dice, round(n12 / sqrt(CAST(n1 * n2 AS DOUBLE)), 6) AS cosine FROM share WHERE p1 < p2", *GRAPH))(lambda s, d: rounded(similarity.overlap_scores(neighbourhood(edges(s, d)))))
query("path_levels", sql("SELECT p1, p2, l FROM chain UNION ALL SELECT DISTINCT p1, p1, 0 FROM share", *CHAINS))(lambda s, d: similarity.path_levels(share(s, d)))
_CH = "SELECT p1, p2, l, round(chain, 6) AS chain FROM chain"
query("chain_scores", sql(_CH, *CHAINS))(lambda s, d: rounded(chain(s, d)))
query("chain_scores_refined", sql(_CH, *CHAINS, kind="refined"))(lambda s, d: rounded(chain(s, d, "refined")))
query("chain_split", sql(_CH, *CHAINS))(lambda s, d: rounded(similarity.chain_scores(share(s, d), form="split")))
query("chain_local", sql(_CH, *CHAINS))(lambda s, d: rounded(similarity.chain_local(share(s, d))))
query("chain_truncated", sql(_CH + " WHERE l <= 2", *CHAINS))(lambda s, d: rounded(similarity.chain_scores(share(s, d), max_level=2)))
_FWD = "fwd AS (SELECT DISTINCT a.p AS p1, b.p AS p2 FROM edges a JOIN edges b ON a.oc = b.sc AND a.p <> b.p)"
_DIRECTED = _levels("SELECT s.p1, s.p2, s.share AS c FROM share s JOIN fwd ON fwd.p1 = s.p1 AND fwd.p2 = s.p2")
query("chain_directed", sql(_CH, *GRAPH, _FWD, _DIRECTED))(lambda s, d: rounded(similarity.chain_scores(similarity.forward_pairs(edges(s, d), share(s, d)))))


@query("chain_either", sql("SELECT p1, p2, round(max(chain), 6) AS chain FROM (SELECT p1, p2, chain FROM chain UNION ALL SELECT p2, p1, chain FROM chain) GROUP BY 1, 2", *GRAPH, _FWD, _DIRECTED))
def _either(s: SparkSession, d: str) -> DataFrame:
    one = similarity.chain_scores(similarity.forward_pairs(edges(s, d), share(s, d))).select("p1", "p2", "chain")
    return rounded(one.unionByName(one.select(F.col("p2").alias("p1"), F.col("p1").alias("p2"), "chain")).groupBy("p1", "p2").agg(F.max("chain").alias("chain")))


def _doubled() -> str:
    parts = ["b0 AS MATERIALIZED (SELECT p1, p2, share AS c FROM share)"]
    for k in range(1, 6):
        parts.append(f"b{k} AS MATERIALIZED (SELECT p1, p2, max(c) AS c FROM (SELECT * FROM b{k - 1} UNION ALL SELECT a.p1, b.p2, a.c * b.c FROM b{k - 1} a JOIN b{k - 1} b ON a.p2 = b.p1 AND a.p1 <> b.p2) GROUP BY 1, 2)")
    return ", ".join(parts)


query("chain_best_path", sql("SELECT x.p1, x.p2, round(coalesce(s.share, x.c), 6) AS chain FROM b5 x LEFT JOIN share s ON s.p1 = x.p1 AND s.p2 = x.p2", *GRAPH, _doubled()))(lambda s, d: rounded(similarity.best_path(share(s, d))))
query("cte_recursive_levels", sql("SELECT p1, p2, l FROM chain WHERE l <= 2", *CHAINS))(lambda s, d: similarity.levels_sql(share(s, d), 2))
query("similarity_matrix", sql("SELECT p1, p2, l, kind, round(sm, 6) AS sm FROM sm", *FULL))(lambda s, d: rounded(matrix(s, d)))
query("sm_profile", sql("SELECT l, count(*) AS n, round(avg(sm), 6) AS mean, round(min(sm), 6) AS least, round(max(sm), 6) AS most FROM sm GROUP BY l", *FULL))(lambda s, d: rounded(similarity.sm_profile(matrix(s, d))))
_ALL = "SELECT a.p AS p1, b.p AS p2, round({}, 6) AS d FROM size a JOIN size b ON a.p <> b.p LEFT JOIN sm ON sm.p1 = a.p AND sm.p2 = b.p"
query("dissimilarity_one_minus", sql(_ALL.format("1 - coalesce(sm.sm, 0)"), *FULL))(lambda s, d: rounded(similarity.dissimilarity(matrix(s, d), preds(s, d))))
query("dissimilarity_reciprocal", sql(_ALL.format("1 / greatest(coalesce(sm.sm, 0), 0.001) - 1"), *FULL))(lambda s, d: rounded(similarity.dissimilarity(matrix(s, d), preds(s, d), "reciprocal")))
_ROWS = "rowd AS (SELECT a.p1, b.p1 AS p2, sum((a.x - b.x) * (a.x - b.x)) AS q FROM dense a JOIN dense b ON a.c = b.c AND a.p1 <> b.p1 GROUP BY 1, 2)"
DENSE = "dense AS MATERIALIZED (SELECT a.p AS p1, b.p AS c, coalesce(sm.sm, 0) AS x FROM size a CROSS JOIN size b LEFT JOIN sm ON sm.p1 = a.p AND sm.p2 = b.p)"
query("dissimilarity_row_sqeuclid", sql("SELECT p1, p2, round(q, 6) AS d FROM rowd", *FULL, DENSE, _ROWS))(lambda s, d: rounded(similarity.dissimilarity(matrix(s, d), preds(s, d), "row_sqeuclid")))
query("dissimilarity_row_euclid", sql("SELECT p1, p2, round(sqrt(q), 5) AS d FROM rowd", *FULL, DENSE, _ROWS))(lambda s, d: rounded(similarity.dissimilarity(matrix(s, d), preds(s, d), "row_euclid"), 5))
query("row_features", sql("SELECT p1 AS p, string_agg(CAST(CAST(round(x * 1000000) AS BIGINT) AS VARCHAR), ',' ORDER BY c) AS features FROM dense GROUP BY 1", *FULL, DENSE))(lambda s, d: features(s, d).select("p", F.concat_ws(",", F.transform("features", lambda x: F.round(x * 1000000).cast("long").cast("string"))).alias("features")))
query("neighbours", sql("SELECT p1, CAST(row_number() OVER (PARTITION BY p1 ORDER BY sm DESC, p2) AS INT) AS rank, p2, round(sm, 6) AS sm FROM sm WHERE p1 <> p2 AND sm > 0.2", *FULL))(lambda s, d: rounded(similarity.neighbours(matrix(s, d))))
query("concept_similarity", sql("SELECT x.c1, x.c2, a.n AS n1, b.n AS n2, x.n12, round(x.n12 * x.n12 / CAST(a.n * b.n AS DOUBLE), 6) AS share FROM (SELECT a.concept AS c1, b.concept AS c2, count(*) AS n12 FROM nbr a JOIN nbr b ON a.p = b.p AND a.concept < b.concept GROUP BY 1, 2) x JOIN (SELECT concept, count(*) AS n FROM nbr GROUP BY 1) a ON a.concept = c1 JOIN (SELECT concept, count(*) AS n FROM nbr GROUP BY 1) b ON b.concept = c2", INC, NBR))(lambda s, d: rounded(similarity.concept_similarity(neighbourhood(edges(s, d)))))
query("reachable", sql("SELECT p1, p2 FROM chain", *CHAINS))(lambda s, d: chain(s, d).select("p1", "p2"))

# clustering --------------------------------------------------------------------------------------------------------------


def _unrolled(k: int, rounds: int) -> str:
    parts = [f"c0 AS MATERIALIZED (SELECT r.rank - 1 AS cluster, d.c, d.x FROM (SELECT p, row_number() OVER (ORDER BY io DESC, p) AS rank FROM pdeg) r JOIN dense d ON d.p1 = r.p WHERE r.rank <= {k})"]
    for i in range(1, rounds + 1):
        parts.append(f"d{i} AS MATERIALIZED (SELECT a.p1 AS p, b.cluster, round(sum((a.x - b.x) * (a.x - b.x)), 9) AS d FROM dense a JOIN c{i - 1} b ON a.c = b.c GROUP BY 1, 2)")
        parts.append(f"a{i} AS MATERIALIZED (SELECT p, CAST(arg_min(cluster, {{'d': d, 'k': cluster}}) AS INT) AS cluster FROM d{i} GROUP BY p)")
        parts.append(f"c{i} AS MATERIALIZED (SELECT a.cluster, d.c, avg(d.x) AS x FROM dense d JOIN a{i} a ON a.p = d.p1 GROUP BY 1, 2)")
    return ", ".join(parts)


@query("lloyd_fixed", sql("SELECT p, cluster FROM a3", *FULL, DENSE, PDEG, _unrolled(4, 3)))
def _lloyd(s: SparkSession, d: str) -> DataFrame:
    rows = settle(kmeans.long_rows(features(s, d)))
    return kmeans.lloyd(rows, kmeans.top_degree_start(graph.predicate_degree(edges(s, d)), 4), 3)[0]


@query("inertia_fixed", sql("SELECT topic AS cluster, round(sum((d.x - m.x) * (d.x - m.x)), 6) AS cost FROM dense d JOIN fixed f ON f.p = d.p1 JOIN (SELECT topic AS t, c, avg(x) AS x FROM dense JOIN fixed ON fixed.p = p1 GROUP BY 1, 2) m ON m.t = f.topic AND m.c = d.c GROUP BY 1", *TOPICS, DENSE))
def _inertia(s: SparkSession, d: str) -> DataFrame:
    rows, assign = kmeans.long_rows(features(s, d)), fixed(s, d).select("p", F.col("topic").alias("cluster"))
    return rounded(kmeans.inertia(rows, assign, rows.join(assign, "p").groupBy("cluster", "dim").agg(F.avg("x").alias("x"))))


query("silhouette_fixed", sql("SELECT p, cluster, parent, round(a, 6) AS a, round(b, 6) AS b, sibling, round(sw, 6) AS sw FROM sw", *JUDGED))(lambda s, d: rounded(fixed_silhouette(s, d)))
query("silhouette_class", sql("SELECT p, round(sw, 6) AS sw, CASE WHEN sw > 0.1 THEN 'well' WHEN sw < -0.1 THEN 'misplaced' ELSE 'border' END AS placed FROM sw", *JUDGED))(lambda s, d: rounded(sil.silhouette_class(fixed_silhouette(s, d)).select("p", "sw", "placed")))
query("topic_width", sql("SELECT parent, cluster AS topic, round(avg(sw), 6) AS sw, count(*) AS n FROM sw GROUP BY 1, 2", *JUDGED))(lambda s, d: rounded(sil.topic_width(fixed_silhouette(s, d))))
query("overall_width", sql("SELECT round(avg(sw), 6) AS sw, count(*) AS n FROM sw", *JUDGED))(lambda s, d: rounded(sil.overall_width(fixed_silhouette(s, d))))
query("sibling_width", sql("SELECT parent, round(sum(w * n) / sum(n), 6) AS nsw, count(*) AS k, CAST(sum(n) AS BIGINT) AS n FROM (SELECT parent, cluster, avg(sw) AS w, count(*) AS n FROM sw GROUP BY 1, 2) GROUP BY 1", *JUDGED))(lambda s, d: rounded(sil.sibling_width(sil.topic_width(fixed_silhouette(s, d)))))
query("contribution", sql("SELECT 'root' AS parent, topic, count(*) AS n, round(count(*) / CAST(sum(count(*)) OVER () AS DOUBLE), 6) AS rate FROM fixed GROUP BY topic", FIXED))(lambda s, d: rounded(tree.contribution(fixed(s, d).groupBy(F.lit("root").alias("parent"), "topic").agg(F.count("*").alias("n")))))
query("topic_labels", sql("SELECT topic, string_agg(p, ' & ' ORDER BY r) AS label FROM (SELECT topic, f.p, row_number() OVER (PARTITION BY topic ORDER BY io DESC, f.p) AS r FROM fixed f JOIN pdeg ON pdeg.p = f.p) WHERE r <= 2 GROUP BY topic", FIXED, PDEG))(lambda s, d: tree.topic_labels(fixed(s, d), graph.predicate_degree(edges(s, d))))
query("duplicate_concepts", sql("SELECT concept, count(*) AS freq, string_agg(topic, ',' ORDER BY topic) AS topics FROM tc GROUP BY 1 HAVING count(*) > 1", INC, NBR, FIXED, TC))(lambda s, d: tree.duplicate_concepts(tree.topic_concepts(edges(s, d), fixed(s, d))))
query("topic_overlap", sql("SELECT a.topic AS t1, b.topic AS t2, count(*) AS n FROM tc a JOIN tc b ON a.concept = b.concept AND a.topic < b.topic GROUP BY 1, 2", INC, NBR, FIXED, TC))(lambda s, d: tree.topic_overlap(tree.topic_concepts(edges(s, d), fixed(s, d))))
# The root's split in SQL. Seeds of all k are the first ones of one farthest-first sequence, so the rounds of all k go together; SQL_ROUNDS are
# more than any k takes on the given tables. Below the root no topic of theirs has the ten predicates that a split needs.
SQL_ROUNDS, SQL_KS = 14, range(2, 17)


def _farthest_first(n: int) -> list[str]:
    parts = ["mid AS (SELECT c, avg(x) AS x FROM dense GROUP BY c)", "g1 AS MATERIALIZED (SELECT 1 AS n, p FROM (SELECT p1 AS p, round(sum((d.x - m.x) * (d.x - m.x)), 9) AS q FROM dense d JOIN mid m ON m.c = d.c GROUP BY 1) ORDER BY q, p LIMIT 1)"]
    for j in range(2, n + 1):
        near = f"SELECT p1 AS p, round(min(q), 9) AS q FROM pairs WHERE p2 IN (SELECT p FROM g{j - 1}) GROUP BY 1"
        parts.append(f"g{j} AS MATERIALIZED (SELECT * FROM g{j - 1} UNION ALL SELECT * FROM (SELECT {j} AS n, p FROM ({near}) ORDER BY q DESC, p LIMIT 1))")
    return parts


def _rounds(n: int) -> list[str]:
    parts = []
    for i in range(1, n + 1):
        far = f"SELECT r.k, d.p1 AS p, r.cluster, round(sum((d.x - r.x) * (d.x - r.x)), 9) AS q FROM dense d JOIN r{i - 1} r ON r.c = d.c GROUP BY 1, 2, 3"
        parts.append(f"l{i} AS MATERIALIZED (SELECT k, p, arg_min(cluster, {{'q': q, 'c': cluster}}) AS cluster FROM ({far}) GROUP BY 1, 2)")
        parts.append(f"r{i} AS MATERIALIZED (SELECT l.k, l.cluster, d.c, avg(d.x) AS x FROM dense d JOIN l{i} l ON l.p = d.p1 GROUP BY 1, 2, 3)")
    return parts


PAIRS = "pairs AS MATERIALIZED (SELECT a.p1, b.p1 AS p2, sum((a.x - b.x) * (a.x - b.x)) AS q FROM dense a JOIN dense b ON a.c = b.c GROUP BY 1, 2)"
FINAL = f"final AS MATERIALIZED (SELECT * FROM l{SQL_ROUNDS})"
LLOYDS = ", ".join(
    [DENSE, PAIRS, *_farthest_first(max(SQL_KS)), "ks AS (SELECT unnest(range(2, 17)) AS k)", f"r0 AS MATERIALIZED (SELECT ks.k, g.n - 1 AS cluster, d.c, d.x FROM ks JOIN g{max(SQL_KS)} g ON g.n <= ks.k JOIN dense d ON d.p1 = g.p)"]
    + _rounds(SQL_ROUNDS) + [FINAL]
)


def _judged(d: str) -> str:
    """Silhouettes of all k, with a dissimilarity d over pairs (of q, or of the matrix's own value v)."""
    return f"""far AS MATERIALIZED (SELECT pairs.p1, pairs.p2, {d} AS d FROM pairs LEFT JOIN sm ON sm.p1 = pairs.p1 AND sm.p2 = pairs.p2 WHERE pairs.p1 <> pairs.p2),
 to_cluster AS (SELECT f.k, far.p1 AS p, f.cluster AS o, avg(far.d) AS m FROM far JOIN final f ON f.p = far.p2 GROUP BY 1, 2, 3),
 ab AS (SELECT f.k, f.p, f.cluster, max(m) FILTER (o = f.cluster) AS a, min(m) FILTER (o <> f.cluster) AS b FROM final f JOIN to_cluster t ON t.k = f.k AND t.p = f.p GROUP BY 1, 2, 3),
 each_sw AS MATERIALIZED (SELECT k, p, cluster, CASE WHEN a IS NULL OR b IS NULL OR greatest(a, b) = 0 THEN 0 ELSE (b - a) / greatest(a, b) END AS sw FROM ab),
 swept AS MATERIALIZED (SELECT k, count(DISTINCT cluster) AS n_clusters, avg(sw) AS nsw FROM each_sw GROUP BY k), best AS MATERIALIZED (SELECT * FROM swept ORDER BY round(nsw, 9) DESC, k LIMIT 1)"""


SPLIT = """parts AS MATERIALIZED (SELECT 'T1_' || dense_rank() OVER (ORDER BY least_p) AS topic, p, sw FROM (SELECT e.p, e.sw, min(e.p) OVER (PARTITION BY e.cluster) AS least_p FROM each_sw e JOIN best ON best.k = e.k WHERE best.nsw >= 0.5 AND (SELECT count(*) FROM size) >= 10)),
 leaf AS MATERIALIZED (SELECT topic, p FROM parts UNION ALL SELECT 'T0_1', p FROM size WHERE NOT EXISTS (SELECT 1 FROM parts)),
 topics AS MATERIALIZED (SELECT 'T0_1' AS topic_id, CAST(NULL AS VARCHAR) AS parent_id, 0 AS level, 1 AS ordinal, (SELECT CAST(n_clusters AS INT) FROM best WHERE nsw >= 0.5) AS k, (SELECT CAST(count(*) AS INT) FROM size) AS n_pred, CAST(NULL AS DOUBLE) AS sw, (SELECT nsw FROM best WHERE nsw >= 0.5) AS nsw, CAST(1 AS DOUBLE) AS contribution
 UNION ALL SELECT topic, 'T0_1', 1, CAST(substr(topic, 4) AS INT), NULL, CAST(count(*) AS INT), avg(sw), NULL, count(*) / CAST((SELECT count(*) FROM size) AS DOUBLE) FROM parts GROUP BY topic)"""
ROOT = (*FULL, PDEG, LLOYDS, _judged("q"))
TREE = (*ROOT, SPLIT)


def leaf_topics(s: SparkSession, d: str) -> DataFrame:
    return tree.leaves(built_tree(s, d))


def refined(select: str, *blocks: str) -> str:
    return sql(select, *TREE, *blocks, kind="refined")


query("topic_tree", refined("SELECT topic_id, parent_id, CAST(level AS INT) AS level, CAST(ordinal AS INT) AS ordinal, k, n_pred, round(sw, 6) AS sw, round(nsw, 6) AS nsw, round(contribution, 6) AS contribution FROM topics"))(lambda s, d: rounded(built_tree(s, d).topics))
query("topic_members", refined("SELECT 'T0_1' AS topic_id, CAST(0 AS INT) AS level, p FROM size UNION ALL SELECT topic, 1, p FROM parts"))(lambda s, d: built_tree(s, d).members)
_COST = f"(SELECT l.k, sum((d.x - r.x) * (d.x - r.x)) AS inertia FROM dense d JOIN final l ON l.p = d.p1 JOIN r{SQL_ROUNDS} r ON r.k = l.k AND r.cluster = l.cluster AND r.c = d.c GROUP BY 1)"
query("tree_sweep", sql(f"SELECT CAST(0 AS INT) AS level, 'T0_1' AS topic, CAST(swept.k AS INT) AS k, CAST(0 AS INT) AS restart, CAST(n_clusters AS INT) AS n_clusters, round(inertia, 6) AS inertia, round(nsw, 6) AS nsw FROM swept JOIN {_COST} c ON c.k = swept.k", *ROOT, kind="refined"))(lambda s, d: rounded(built_tree(s, d).sweeps))
query("tree_shape", refined("SELECT CAST(level AS INT) AS level, count(*) AS topics, count(*) AS frontier, CAST(sum(n_pred) AS BIGINT) AS predicates FROM topics GROUP BY level"))(lambda s, d: tree.tree_shape(built_tree(s, d).topics))
query("tree_labels", refined("SELECT topic, string_agg(p, ' & ' ORDER BY r) AS label FROM (SELECT topic, leaf.p, row_number() OVER (PARTITION BY topic ORDER BY io DESC, leaf.p) AS r FROM leaf JOIN pdeg ON pdeg.p = leaf.p) WHERE r <= 2 GROUP BY topic"))(lambda s, d: tree.topic_labels(leaf_topics(s, d), graph.predicate_degree(edges(s, d, "refined"))))
query("tree_sibling_width", refined("SELECT parent, round(sum(w * n) / sum(n), 6) AS nsw, count(*) AS k, CAST(sum(n) AS BIGINT) AS n FROM (SELECT 'T0_1' AS parent, topic, avg(sw) AS w, count(*) AS n FROM parts GROUP BY topic) GROUP BY 1"))(lambda s, d: rounded(sil.sibling_width(built_tree(s, d).topics.where("parent_id is not null").select(F.col("parent_id").alias("parent"), "topic_id", "sw", F.col("n_pred").cast("long").alias("n")))))
_LEAF_TC = "tc AS (SELECT DISTINCT leaf.topic, n.concept FROM leaf JOIN nbr n ON n.p = leaf.p)"
query("tree_duplicate_concepts", refined("SELECT concept, count(*) AS freq, string_agg(topic, ',' ORDER BY topic) AS topics FROM tc GROUP BY 1 HAVING count(*) > 1", _LEAF_TC))(lambda s, d: tree.duplicate_concepts(tree.topic_concepts(edges(s, d, "refined"), leaf_topics(s, d))))
query("tree_topic_overlap", refined("SELECT a.topic AS t1, b.topic AS t2, count(*) AS n FROM tc a JOIN tc b ON a.concept = b.concept AND a.topic < b.topic GROUP BY 1, 2", _LEAF_TC))(lambda s, d: tree.topic_overlap(tree.topic_concepts(edges(s, d, "refined"), leaf_topics(s, d))))

READINGS = {"one_minus": "1 - coalesce(sm.sm, 0)", "reciprocal": "1 / greatest(coalesce(sm.sm, 0), 0.001) - 1", "row_euclid": "sqrt(q)", "row_sqeuclid": "q"}


def _reading_sql(kind: str, how: str) -> str:
    select = f"SELECT '{kind}' AS ontology, '{how}' AS dissimilarity, CAST(k AS INT) AS k, round(nsw, 6) AS nsw, nsw >= 0.5 AS splits FROM best"
    return "SELECT * FROM (" + sql(select, *FULL, LLOYDS, _judged(READINGS[how]), kind=kind) + ")"


@query("tree_readings", " UNION ALL ".join(_reading_sql(k, h) for k in ("base", "refined") for h in READINGS))
def _readings(s: SparkSession, d: str) -> DataFrame:
    """(ontology, dissimilarity, k, nsw) of the root's best split under every reading, those that do not split too."""
    out = None
    for kind in ("base", "refined"):
        root = preds(s, d, kind).select(F.lit("root").alias("topic"), "p")
        for how in READINGS:
            best = tree.choose_k(tree.best_restarts(kmeans.level_sweep(root, features(s, d, kind), tuple(SQL_KS), dissimilarity=how)))
            one = best.select(F.lit(kind).alias("ontology"), F.lit(how).alias("dissimilarity"), "k", "nsw", (F.col("nsw") >= 0.5).alias("splits"))
            out = one if out is None else out.unionByName(one)
    return rounded(out)


_ROWDIS = "dis AS MATERIALIZED (SELECT p1, p2, q AS d FROM rowd)"


@query("silhouette_fast", sql("SELECT round(avg(sw), 6) AS sw FROM sw", *TOPICS, DENSE, _ROWS, _ROWDIS, SIL))
def _fast(s: SparkSession, d: str) -> DataFrame:
    assign = fixed(s, d).select("p", F.dense_rank().over(W.orderBy("topic")).alias("cluster"))
    return rounded(s.createDataFrame([(sil.silhouette_fast(features(s, d), assign),)], "sw double"))


query("silhouette_cases", ORACLES["silhouette_fixed"])(lambda s, d: rounded(sil.silhouette(similarity.dissimilarity(matrix(s, d), preds(s, d)), fixed(s, d).select("p", F.col("topic").alias("cluster"), F.lit("root").alias("parent")), "cases")))
query("silhouette_sample", sql("SELECT count(*) AS n, round(avg(sw), 6) AS sw, round(1.96 * stddev_samp(sw) / sqrt(count(*)), 6) AS half FROM sw WHERE substr(md5(p || '/0'), 1, 8) < '80000000'", *JUDGED))(lambda s, d: rounded(sil.silhouette_sample(similarity.dissimilarity(matrix(s, d), preds(s, d)), fixed(s, d).select("p", F.col("topic").alias("cluster"), F.lit("root").alias("parent")), 0.5)))
query("tree_stop_above", sql("SELECT topic_id, parent_id, CAST(level AS INT) AS level, CAST(ordinal AS INT) AS ordinal, k, n_pred, round(sw, 6) AS sw, round(nsw, 6) AS nsw, round(contribution, 6) AS contribution FROM topics", *ROOT, SPLIT.replace("nsw >= 0.5", "n_clusters >= 2"), kind="refined"))(lambda s, d: rounded(tree.topic_tree(preds(s, d, "refined"), features(s, d, "refined"), rule="stop_above").topics))
query("tree_random_start")(lambda s, d: rounded(tree.topic_tree(preds(s, d, "refined"), features(s, d, "refined"), init="random", restarts=8).topics))
query("tree_weighted_features")(lambda s, d: rounded(tree.topic_tree(preds(s, d, "refined"), features(s, d, "refined"), features_of="topic", feature_weight="variance").topics))
query("ml_kmeans")(lambda s, d: kmeans.ml_kmeans(features(s, d, "refined"), 8))
query("width_curve")(lambda s, d: once(s, (d, "curve"), lambda: settle(baselines.width_curve(features(s, d, "refined")))))
query("width_curve_nodes")(lambda s, d: baselines.node_curves(tree.inner_nodes(built_tree(s, d)), features(s, d, "refined")))
query("width_stability")(lambda s, d: baselines.stability(QUERIES["width_curve"](s, d)))
query("flat_kmeans", sql("SELECT 'kmeans' AS algorithm, CAST(8 AS INT) AS k, p, CAST(dense_rank() OVER (ORDER BY cluster) - 1 AS INT) AS cluster, round(sw, 6) AS sw FROM each_sw WHERE k = 8", *ROOT, kind="refined"))(lambda s, d: rounded(baselines.clusterings(features(s, d, "refined"), ("kmeans",), (8,))))
for _a in ("medoids", "sampled_medoids", "single", "complete", "average", "ward", "divisive"):
    query({"medoids": "pam", "sampled_medoids": "clara", "divisive": "divisive"}.get(_a, f"agglomerative_{_a}"))(lambda s, d, a=_a: baselines.clusterings(features(s, d, "refined"), (a,), (8,)))
query("bisecting")(lambda s, d: baselines.bisecting(features(s, d, "refined"), 8))
query("power_iteration")(lambda s, d: baselines.power_iteration(matrix(s, d, "refined"), 4))
query("random_partition", sql("SELECT p, CAST((row_number() OVER (ORDER BY md5(p || '/0'), p) - 1) % 8 AS INT) AS cluster FROM (SELECT DISTINCT p FROM edges)"))(lambda s, d: baselines.random_partition(preds(s, d), 8))
query("concept_topics")(lambda s, d: baselines.concept_topics(neighbourhood(edges(s, d)), 6))
query("spanning_tree")(lambda s, d: baselines.spanning_tree(similarity.dissimilarity(matrix(s, d), preds(s, d))))
query("permutation_test")(lambda s, d: baselines.permutation_test(features(s, d), fixed(s, d).select("p", F.col("topic").alias("cluster"))))

# ranking -----------------------------------------------------------------------------------------------------------------

_CRIT = f"""inside AS (SELECT topic, concept, count(DISTINCT f.p) AS n FROM fixed f JOIN nbr ON nbr.p = f.p GROUP BY 1, 2), owner AS (SELECT topic, concept FROM inside QUALIFY row_number() OVER (PARTITION BY concept ORDER BY n DESC, topic) = 1),
topc AS (SELECT concept FROM (SELECT concept, rank() OVER (ORDER BY io DESC) AS r FROM cdeg) WHERE r <= 20), topp AS (SELECT p FROM (SELECT p, row_number() OVER (ORDER BY io DESC, p) AS r FROM pdeg) WHERE r <= 20),
crit AS (SELECT t.topic, (SELECT count(*) FROM fixed f JOIN topp ON topp.p = f.p WHERE f.topic = t.topic) AS top_predicates, (SELECT count(*) FROM owner o JOIN topc ON topc.concept = o.concept WHERE o.topic = t.topic) AS top_concepts,
 CASE WHEN t.n > 1 THEN coalesce((SELECT sum(sm.sm) FROM sm JOIN fixed a ON a.p = sm.p1 JOIN fixed b ON b.p = sm.p2 WHERE sm.p1 <> sm.p2 AND a.topic = t.topic AND b.topic = t.topic), 0) / (t.n * (t.n - 1)) END AS similarity,
 (SELECT avg(sw) FROM sw WHERE cluster = t.topic) AS width,
 (SELECT {DENSITY} FROM (SELECT count(*) AS e, count(DISTINCT concept) AS c, count(DISTINCT inc.p) AS p FROM inc JOIN fixed f ON f.p = inc.p WHERE f.topic = t.topic)) AS density FROM (SELECT topic, count(*) AS n FROM fixed GROUP BY 1) t)"""
_RANKS = ", ".join(f"CAST(rank() OVER (ORDER BY round({c}, 9) DESC NULLS LAST) AS INT) AS rank_{c}" for c in ranking.CRITERIA)


def fixed_ranking(s: SparkSession, d: str) -> DataFrame:
    widths = sil.topic_width(fixed_silhouette(s, d)).select("topic", "sw")
    return ranking.integrated_rank(ranking.criteria(edges(s, d), fixed(s, d), matrix(s, d), widths))


query(
    "topic_ranking",
    sql(f"SELECT *, CAST(row_number() OVER (ORDER BY mean_rank, topic) AS INT) AS overall FROM (SELECT topic, top_predicates, top_concepts, round(similarity, 6) AS similarity, round(width, 6) AS width, round(density, 6) AS density, {', '.join('rank_' + c for c in ranking.CRITERIA)}, round(({' + '.join('rank_' + c for c in ranking.CRITERIA)}) / 5.0, 6) AS mean_rank FROM (SELECT *, {_RANKS} FROM crit))", *JUDGED, PDEG, CDEG, _CRIT),
)(lambda s, d: rounded(fixed_ranking(s, d)))
_WEIGHTS = {"density": 2.0, "width": 0.5}
_WEIGHED = " + ".join(f"{_WEIGHTS.get(c, 1.0)} * rank_{c}" for c in ranking.CRITERIA)
query("topic_ranking_weighted", sql(f"SELECT topic, round(mean_rank, 6) AS mean_rank, CAST(row_number() OVER (ORDER BY mean_rank, topic) AS INT) AS overall FROM (SELECT topic, round(({_WEIGHED}) / {sum(_WEIGHTS.get(c, 1.0) for c in ranking.CRITERIA)}, 9) AS mean_rank FROM (SELECT *, {_RANKS} FROM crit))", *JUDGED, PDEG, CDEG, _CRIT))(
    lambda s, d: rounded(ranking.integrated_rank(ranking.criteria(edges(s, d), fixed(s, d), matrix(s, d), sil.topic_width(fixed_silhouette(s, d)).select("topic", "sw")), _WEIGHTS).select("topic", "mean_rank", "overall"))
)
query(
    "top_table",
    sql("""SELECT r.rank, r.p, r.io, f.topic, c.concept, c.concept_rank FROM (SELECT CAST(row_number() OVER (ORDER BY io DESC, p) AS INT) AS rank, p, io FROM pdeg QUALIFY rank <= 20) r LEFT JOIN fixed f ON f.p = r.p LEFT JOIN (SELECT concept, CAST(rank() OVER (ORDER BY io DESC) AS INT) AS concept_rank FROM cdeg) c ON lower(c.concept) = lower(r.p)""", INC, PDEG, CDEG, FIXED),
)(lambda s, d: ranking.top_table(edges(s, d), fixed(s, d)))


_OF_TREE = ("fixed AS (SELECT topic, p FROM leaf)", "sw AS (SELECT topic AS cluster, p, sw FROM parts)", CDEG)
_RANKED = f"""SELECT *, CAST(row_number() OVER (ORDER BY mean_rank, topic) AS INT) AS overall FROM (SELECT topic, top_predicates, top_concepts, round(similarity, 6) AS similarity, round(width, 6) AS width, round(density, 6) AS density,
 {', '.join('rank_' + c for c in ranking.CRITERIA)}, round(({' + '.join('rank_' + c for c in ranking.CRITERIA)}) / 5.0, 6) AS mean_rank FROM (SELECT *, {_RANKS} FROM crit))"""


@query("tree_ranking", refined(_RANKED, *_OF_TREE, _CRIT))
def tree_ranking(s: SparkSession, d: str) -> DataFrame:
    """The ranking of the built tree's leaves on the refined graph."""
    made = built_tree(s, d)
    widths = made.topics.select(F.col("topic_id").alias("topic"), "sw")
    return rounded(ranking.integrated_rank(ranking.criteria(edges(s, d, "refined"), tree.leaves(made), matrix(s, d, "refined"), widths)))


# sketches, weaving, terms ---------------------------------------------------------------------------------------------------

query("share_theta")(lambda s, d: sketches.share_scores_theta(neighbourhood(edges(s, d))))
query("share_lsh_near", sql(_SH + " AND n12 / CAST(n1 + n2 - n12 AS DOUBLE) >= 0.5", *GRAPH))(lambda s, d: rounded(sketches.share_scores_lsh(neighbourhood(edges(s, d))).where(F.col("n12") / (F.col("n1") + F.col("n2") - F.col("n12")) >= 0.5).select("p1", "p2", "n1", "n2", "n12", "share")))
query("share_lsh")(lambda s, d: sketches.share_scores_lsh(neighbourhood(edges(s, d))))
query("share_theta_error")(lambda s, d: sketches.share_error(neighbourhood(edges(s, d)), sketches.share_scores_theta(neighbourhood(edges(s, d)))))
query("topic_graph", sql("SELECT DISTINCT topic, sc, e.p, oc FROM edges e JOIN fixed f ON f.p = e.p", FIXED))(lambda s, d: weaver.topic_graph(edges(s, d), fixed(s, d)))
query("weave_seeds", sql("SELECT topic, CAST(row_number() OVER (PARTITION BY topic ORDER BY io DESC, f.p) AS INT) AS rank, f.p FROM fixed f JOIN pdeg ON pdeg.p = f.p QUALIFY rank <= 10", FIXED, PDEG))(lambda s, d: weaver.seeds(fixed(s, d), graph.predicate_degree(edges(s, d)), 10))
query(
    "weave_fixed",
    "WITH RECURSIVE " + sql("SELECT topic, p FROM reach", *TOPICS, PDEG, "seed AS (SELECT topic, f.p FROM fixed f JOIN pdeg ON pdeg.p = f.p QUALIFY row_number() OVER (PARTITION BY topic ORDER BY io DESC, f.p) = 1)", "hop AS MATERIALIZED (SELECT a.topic, sm.p1, sm.p2 FROM sm JOIN fixed a ON a.p = sm.p1 JOIN fixed b ON b.p = sm.p2 AND b.topic = a.topic WHERE sm.p1 <> sm.p2 AND sm.sm > 0.2)", "reach AS (SELECT topic, p FROM seed UNION SELECT r.topic, h.p2 FROM reach r JOIN hop h ON h.topic = r.topic AND h.p1 = r.p)")[len("WITH "):],
)(lambda s, d: weaver.weave_all(fixed(s, d), matrix(s, d), graph.predicate_degree(edges(s, d))).select("topic", "p"))


def _reach_sql(members: str, seeds: int, betas: str, *blocks: str) -> str:
    """What walks from the topics' best seeds reach, by seed and threshold; the order of steps aside."""
    seed = f"seed AS (SELECT topic, f.p FROM {members} f JOIN pdeg ON pdeg.p = f.p QUALIFY row_number() OVER (PARTITION BY topic ORDER BY io DESC, f.p) <= {seeds})"
    hop = f"hop AS MATERIALIZED (SELECT a.topic, sm.p1, sm.p2, sm.sm FROM sm JOIN {members} a ON a.p = sm.p1 JOIN {members} b ON b.p = sm.p2 AND b.topic = a.topic WHERE sm.p1 <> sm.p2)"
    reach = f"reach AS (SELECT topic, p AS seed, beta, p FROM seed, (SELECT unnest({betas}) AS beta) UNION SELECT r.topic, r.seed, r.beta, h.p2 FROM reach r JOIN hop h ON h.topic = r.topic AND h.p1 = r.p AND h.sm > r.beta)"
    return "WITH RECURSIVE " + sql("SELECT topic, seed, CAST(beta AS DOUBLE) AS beta, p FROM reach", *TOPICS, PDEG, *blocks, seed, hop, reach)[len("WITH ") :]


MIXED = ("lang", "text", "role", "conv", "source")
query("weave_reach", _reach_sql("fixed", 10, "[0.1, 0.2, 0.4]"))(lambda s, d: QUERIES["weave_steps"](s, d).select("topic", "seed", "beta", "p"))
query("weave_cross_domain_reach", _reach_sql("mixed", 1, "[0.05]", f"mixed AS (SELECT DISTINCT 'mixed' AS topic, p FROM edges WHERE p IN {MIXED})"))(lambda s, d: cross_domain(s, d).select("topic", "seed", "beta", "p"))


@query("weave_cross_domain")
def cross_domain(s: SparkSession, d: str) -> DataFrame:
    """A walk over one topic of predicates that several namespaces have: lang, text and role."""
    members = s.createDataFrame([("mixed", p) for p in MIXED], "topic string, p string")
    return weaver.weave_all(members, matrix(s, d), graph.predicate_degree(edges(s, d)), 1, (0.05,))


query("weave_steps")(lambda s, d: weaver.weave_all(fixed(s, d), matrix(s, d), graph.predicate_degree(edges(s, d)), 10, (0.1, 0.2, 0.4)))
query("degree_query", sql("SELECT topic, CAST(row_number() OVER (PARTITION BY topic ORDER BY io DESC, f.p) AS INT) AS step, f.p FROM fixed f JOIN pdeg ON pdeg.p = f.p QUALIFY step <= 3", FIXED, PDEG))(lambda s, d: weaver.degree_query(fixed(s, d), graph.predicate_degree(edges(s, d))))
query("normalise_terms")(lambda s, d: normalise.normalise_terms(edges(s, d), 0.6))
query(
    "cross_domain_chains",
    sql("SELECT p1, p2, l, round(sm, 6) AS sm, array_to_string(a.s, '+') AS ns1, array_to_string(b.s, '+') AS ns2 FROM sm JOIN nss a ON a.p = p1 JOIN nss b ON b.p = p2 WHERE p1 < p2 AND NOT list_has_any(a.s, b.s)", *FULL, "nss AS (SELECT p, list_sort(list(DISTINCT ns)) AS s FROM edges GROUP BY p)"),
)(lambda s, d: rounded(normalise.cross_domain_chains(matrix(s, d), edges(s, d).select("p", "ns"))))
query("endpoint_stats", sql("SELECT p, CAST(sum(n_facts) AS BIGINT) AS facts, count(DISTINCT sc) AS subjects_of, count(DISTINCT oc) AS objects_of FROM edges GROUP BY p"))(lambda s, d: normalise.endpoint_stats(edges(s, d)))
