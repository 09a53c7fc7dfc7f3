"""Relational, scalar, source and sink operators around the methods, each as a query with SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import text, udfs
from ..operators import baselines, normalise, relational, sketches, vectors
from ..operators.ontology import build_facts, incidence, neighbourhood
from ..sources import tables
from ..sources.tables import load_table as load
from . import methods as m
from .workloads import brand_links

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None, f: Callable) -> None:
    QUERIES[name] = f
    if sql:
        ORACLES[name] = sql


day = lambda c: F.date_format(c, "yyyy-MM-dd")
C = F.col
BIG = "CAST({} AS BIGINT) AS {}"

# sources and sinks ------------------------------------------------------------------------------------------------------------

query("src_parquet_count", " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n FROM {n}" for n in tables.NAMES), lambda s, d: tables.counts(s, d))
_NF = "SELECT 'Nation:' || n_nationkey AS s, 'name' AS p, n_name AS o FROM nation UNION ALL SELECT 'Nation:' || n_nationkey, 'region', 'Region:' || n_regionkey FROM nation"
query("src_facts_text", _NF, lambda s, d: tables.read_facts_text(s, tables.write_facts_text(build_facts(s, d, tables=("nation",)), tables.scratch(s, "facts-text"))))
for _f in ("csv", "json", "orc", "parquet"):
    query(f"src_roundtrip_{_f}", "SELECT * FROM nation", lambda s, d, f=_f: tables.roundtrip(load(s, d, "nation"), f))
query("sink_partitioned", f"SELECT p, count(*) AS n FROM ({_NF}) GROUP BY p", lambda s, d: s.read.parquet(tables.write_facts(build_facts(s, d, tables=("nation",)), tables.scratch(s, "facts"))).groupBy("p").agg(F.count("*").alias("n")))


def _bucketed(s: SparkSession, d: str) -> DataFrame:
    """Both sides bucketed by the key, so the join needs no exchange."""
    for name, key in (("orders", "o_orderkey"), ("lineitem", "l_orderkey")):
        load(s, d, name).write.mode("overwrite").option("path", tables.scratch(s, f"bucketed-{name}")).bucketBy(8, key).sortBy(key).saveAsTable(f"predtopics_{name}")
    return s.table("predtopics_orders").join(s.table("predtopics_lineitem"), C("o_orderkey") == C("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


query("sink_bucketed", "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1", _bucketed)
query("sql_views", "SELECT r_name, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1", lambda s, d: (tables.register(s, d, "v_"), s.sql("SELECT r_name, count(*) AS n FROM v_nation JOIN v_region ON n_regionkey = r_regionkey GROUP BY 1"))[1])

# projection and filters ---------------------------------------------------------------------------------------------------------

query("proj_rename_cast", "SELECT o_orderkey AS id, CAST(o_custkey AS VARCHAR) AS customer, CAST(round(o_totalprice) AS BIGINT) AS price FROM orders", lambda s, d: load(s, d, "orders").select(C("o_orderkey").alias("id"), C("o_custkey").cast("string").alias("customer"), F.round("o_totalprice").cast("long").alias("price")))
query("filter_compound", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE (l_quantity BETWEEN 10 AND 20 OR l_returnflag IN ('A')) AND NOT l_linestatus = 'O'", lambda s, d: load(s, d, "lineitem").where((C("l_quantity").between(10, 20) | C("l_returnflag").isin("A")) & ~(C("l_linestatus") == "O")).select("l_orderkey", "l_linenumber", "l_quantity"))
query("filter_null_safe", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL", lambda s, d: load(s, d, "documents", ["doc_id"]).join(load(s, d, "labels"), "doc_id", "left").where(C("quality").eqNullSafe(F.lit(None))).select("doc_id"))
query("filter_like_regex", "SELECT p_partkey FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_type, '^[A-M]')", lambda s, d: load(s, d, "part").where(C("p_name").like("%a%") & C("p_type").rlike("^[A-M]")).select("p_partkey"))

# joins --------------------------------------------------------------------------------------------------------------------------

query("join_broadcast", "SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1", lambda s, d: relational.join(load(s, d, "supplier"), load(s, d, "nation"), C("s_nationkey") == C("n_nationkey"), strategy="broadcast").groupBy("n_name").agg(F.count("*").alias("n")))
query("join_sort_merge", "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1", lambda s, d: relational.join(load(s, d, "lineitem", ["l_orderkey"]), load(s, d, "orders", ["o_orderkey", "o_orderstatus"]), C("l_orderkey") == C("o_orderkey"), strategy="merge").groupBy("o_orderstatus").agg(F.count("*").alias("n")))
query("join_shuffle_hash", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1", lambda s, d: relational.join(load(s, d, "orders", ["o_custkey"]), load(s, d, "customer", ["c_custkey", "c_mktsegment"]), C("o_custkey") == C("c_custkey"), strategy="shuffle_hash").groupBy("c_mktsegment").agg(F.count("*").alias("n")))
for _h, _q in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    query(f"join_{_h}", f"SELECT d.doc_id, l.label_id, l.quality FROM documents d {_q} JOIN (SELECT doc_id + 3 AS label_id, quality FROM labels) l ON d.doc_id = l.label_id", lambda s, d, h=_h: load(s, d, "documents", ["doc_id"]).join(load(s, d, "labels").select((C("doc_id") + 3).alias("label_id"), "quality"), C("doc_id") == C("label_id"), h))
for _h, _q in (("semi", "IN"), ("anti", "NOT IN")):
    query(f"join_{_h}", f"SELECT c_custkey FROM customer WHERE c_custkey {_q} (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)", lambda s, d, h=_h: load(s, d, "customer", ["c_custkey"]).join(load(s, d, "orders").where("o_totalprice > 300000"), C("c_custkey") == C("o_custkey"), f"left_{h}"))
query("join_cross", "SELECT a.r_name AS a, b.r_name AS b FROM region a, region b", lambda s, d: load(s, d, "region").select(C("r_name").alias("a")).crossJoin(load(s, d, "region").select(C("r_name").alias("b"))))
query("join_theta", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal > b.s_acctbal", lambda s, d: load(s, d, "supplier").select(C("s_suppkey").alias("a"), C("s_nationkey").alias("n"), C("s_acctbal").alias("x")).join(load(s, d, "supplier").select(C("s_suppkey").alias("b"), C("s_nationkey").alias("n"), C("s_acctbal").alias("y")), "n").where("x > y").select("a", "b"))
query("join_range", "SELECT p_partkey, CAST(floor(p_retailprice / 250) AS BIGINT) AS band FROM part WHERE p_retailprice >= 0 AND p_retailprice < 5000", lambda s, d: relational.range_join(load(s, d, "part", ["p_partkey", "p_retailprice"]), s.range(20).select(C("id").alias("band"), (C("id") * 250.0).alias("lo"), ((C("id") + 1) * 250.0).alias("hi")), "p_retailprice", "lo", "hi", 100.0).select("p_partkey", "band"))
_ev = lambda s, d, kind: load(s, d, "events", ["event_id", "user_id", "event_type", "ts"]).where(C("event_type") == kind)
query("join_interval", "SELECT a.event_id AS error_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'error' AND b.event_type = 'purchase'", lambda s, d: relational.interval_join(_ev(s, d, "error").select("user_id", "ts", C("event_id").alias("error_id")), _ev(s, d, "purchase").select("user_id", C("ts").alias("ts2"), C("event_id").alias("purchase_id")), "user_id", "ts", 3600, "ts2").select("error_id", "purchase_id"))
query("join_asof", "SELECT a.event_id, b.view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') a LEFT JOIN LATERAL (SELECT event_id AS view_id FROM events v WHERE v.event_type = 'view' AND v.user_id = a.user_id AND v.ts <= a.ts ORDER BY v.ts DESC, v.event_id DESC LIMIT 1) b ON true", lambda s, d: relational.asof_join(_ev(s, d, "purchase").select("user_id", "ts", "event_id"), _ev(s, d, "view").select("user_id", "ts", C("event_id").alias("view_id")), "user_id", "ts", ["view_id"]).select("event_id", "view_id"))
query("join_self_concept", m.sql("SELECT a.p AS p1, b.p AS p2, a.concept FROM nbr a JOIN nbr b ON a.concept = b.concept AND a.p < b.p", m.INC, m.NBR), lambda s, d: neighbourhood(m.edges(s, d)).withColumnRenamed("p", "p1").join(neighbourhood(m.edges(s, d)).withColumnRenamed("p", "p2"), "concept").where("p1 < p2"))
query("join_multiway_star", "SELECT r_name, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1", lambda s, d: load(s, d, "lineitem", ["l_orderkey", "l_extendedprice"]).join(load(s, d, "orders", ["o_orderkey", "o_custkey"]), C("l_orderkey") == C("o_orderkey")).join(load(s, d, "customer", ["c_custkey", "c_nationkey"]), C("o_custkey") == C("c_custkey")).join(F.broadcast(load(s, d, "nation")), C("c_nationkey") == C("n_nationkey")).join(F.broadcast(load(s, d, "region")), C("n_regionkey") == C("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total")))
query("join_lateral_topk", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)", lambda s, d: relational.topk(load(s, d, "orders", ["o_custkey", "o_orderkey", "o_totalprice"]), ["o_custkey"], [F.desc("o_totalprice"), C("o_orderkey")], 2).join(load(s, d, "customer", ["c_custkey"]), C("o_custkey") == C("c_custkey")).select("c_custkey", "o_orderkey"))

# aggregates -----------------------------------------------------------------------------------------------------------------------

query("agg_basic", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, count(*) AS n, min(l_discount) AS low, max(l_tax) AS high FROM lineitem GROUP BY 1, 2", lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.count("*").alias("n"), F.min("l_discount").alias("low"), F.max("l_tax").alias("high")))
query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1", lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")))
query("agg_filter_clause", "SELECT o_orderpriority, count(*) FILTER (o_totalprice > 200000) AS high, round(coalesce(sum(o_totalprice) FILTER (o_orderstatus = 'F'), 0), 2) AS done FROM orders GROUP BY 1", lambda s, d: load(s, d, "orders").groupBy("o_orderpriority").agg(F.count_if(C("o_totalprice") > 200000).alias("high"), F.round(F.coalesce(F.sum(F.when(C("o_orderstatus") == "F", C("o_totalprice"))), F.lit(0.0)), 2).alias("done")))
query("agg_min_max_by", "SELECT o_custkey, arg_min(o_orderkey, {'a': o_totalprice, 'b': o_orderkey}) AS cheapest, arg_max(o_orderkey, {'a': o_totalprice, 'b': o_orderkey}) AS dearest FROM orders GROUP BY 1", lambda s, d: load(s, d, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest")))
query("agg_stats", "SELECT p_brand, round(var_samp(p_retailprice), 4) AS v, round(stddev_samp(p_retailprice), 4) AS sd, round(corr(p_size, p_retailprice), 6) AS r, round(covar_samp(p_size, p_retailprice), 4) AS c FROM part GROUP BY 1", lambda s, d: load(s, d, "part").groupBy("p_brand").agg(F.round(F.variance("p_retailprice"), 4).alias("v"), F.round(F.stddev("p_retailprice"), 4).alias("sd"), F.round(F.corr("p_size", "p_retailprice"), 6).alias("r"), F.round(F.covar_samp("p_size", "p_retailprice"), 4).alias("c")))
query("agg_percentile", "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.25), 4) AS q1, round(quantile_cont(l_extendedprice, 0.5), 4) AS q2, round(quantile_cont(l_extendedprice, 0.75), 4) AS q3 FROM lineitem GROUP BY 1", lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(*[F.round(F.percentile("l_extendedprice", x), 4).alias(n) for n, x in (("q1", 0.25), ("q2", 0.5), ("q3", 0.75))]))
query("agg_collect", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1", lambda s, d: load(s, d, "nation").groupBy("n_regionkey").agg(F.concat_ws(",", F.array_sort(F.collect_list("n_name"))).alias("names")))
#: Estimates are given as whether they are within a tenth of the exact value, next to that.
CLOSE = "SELECT l_returnflag, count(DISTINCT l_partkey) AS exact, true AS close FROM lineitem GROUP BY 1"


def near(df: DataFrame, room: float = 0.1) -> DataFrame:
    return df.select("l_returnflag", "exact", (F.abs(C("told") - C("exact")) <= room * C("exact")).alias("close"))


query("agg_approx_distinct", CLOSE, lambda s, d: near(load(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("told"), F.count_distinct("l_partkey").alias("exact"))))
query("agg_hll", CLOSE, lambda s, d: near(load(s, d, "lineitem").groupBy("l_returnflag").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)).alias("told"), F.count_distinct("l_partkey").alias("exact"))))
query("agg_theta", CLOSE, lambda s, d: near(load(s, d, "lineitem").groupBy("l_returnflag").agg(F.theta_sketch_estimate(F.theta_sketch_agg("l_partkey")).alias("told"), F.count_distinct("l_partkey").alias("exact"))))
query("agg_kll", "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS exact, true AS close FROM lineitem GROUP BY 1", lambda s, d: near(load(s, d, "lineitem").groupBy("l_returnflag").agg(F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("l_extendedprice"), F.lit(0.5)).alias("told"), F.percentile("l_extendedprice", 0.5).alias("exact"))).withColumn("exact", F.round("exact", 4)))
_OC = "orders JOIN customer ON o_custkey = c_custkey"
_oc = lambda s, d: load(s, d, "orders", ["o_custkey", "o_orderstatus"]).join(load(s, d, "customer", ["c_custkey", "c_mktsegment"]), C("o_custkey") == C("c_custkey"))
for _h in ("cube", "rollup"):
    query(f"agg_{_h}", f"SELECT c_mktsegment, o_orderstatus, CAST(grouping(c_mktsegment, o_orderstatus) AS BIGINT) AS gid, count(*) AS n FROM {_OC} GROUP BY {_h}(c_mktsegment, o_orderstatus)", lambda s, d, h=_h: relational.multi_group(_oc(s, d), ["c_mktsegment", "o_orderstatus"], h, F.count("*").alias("n")))
query("agg_grouping_sets", f"SELECT c_mktsegment, o_orderstatus, count(*) AS n FROM {_OC} GROUP BY GROUPING SETS ((c_mktsegment), (o_orderstatus), ())", lambda s, d: _oc(s, d).groupingSets([[C("c_mktsegment")], [C("o_orderstatus")], []], C("c_mktsegment"), C("o_orderstatus")).agg(F.count("*").alias("n")))
_KINDS = ["click", "error", "purchase", "signup", "view"]
query("agg_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS {k}" for k in _KINDS) + " FROM events GROUP BY user_id", lambda s, d: load(s, d, "events").groupBy("user_id").pivot("event_type", _KINDS).agg(F.count("event_id")).na.fill(0))
query("agg_unpivot", "SELECT n_nationkey, k, v FROM (SELECT n_nationkey, n_name, CAST(n_regionkey AS VARCHAR) AS n_regionkey FROM nation) UNPIVOT (v FOR k IN (n_name, n_regionkey))", lambda s, d: load(s, d, "nation").select("n_nationkey", "n_name", C("n_regionkey").cast("string").alias("n_regionkey")).unpivot("n_nationkey", ["n_name", "n_regionkey"], "k", "v"))
query("agg_having", m.sql("SELECT concept, count(DISTINCT p) AS n FROM inc GROUP BY 1 HAVING count(DISTINCT p) >= 2", m.INC), lambda s, d: incidence(m.edges(s, d)).groupBy("concept").agg(F.count_distinct("p").alias("n")).where("n >= 2"))
query("agg_mode", "SELECT conv_id, arg_max(role, {'n': n, 'r': role}) AS role FROM (SELECT conv_id, role, count(*) AS n FROM conversations GROUP BY 1, 2) GROUP BY 1", lambda s, d: load(s, d, "conversations").groupBy("conv_id", "role").agg(F.count("*").alias("n")).groupBy("conv_id").agg(F.max_by("role", F.struct("n", "role")).alias("role")))
query("agg_bool", "SELECT conv_id, bool_and(length(text) > 20) AS every_long, bool_or(role = 'system') AS any_system FROM conversations GROUP BY 1", lambda s, d: load(s, d, "conversations").groupBy("conv_id").agg(F.bool_and(F.length("text") > 20).alias("every_long"), F.bool_or(C("role") == "system").alias("any_system")))

# windows, order, sets -----------------------------------------------------------------------------------------------------------

_w = lambda: W.orderBy(F.desc("io"), "p")
query(
    "win_rank_family", m.sql("SELECT p, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER (ORDER BY io DESC) AS INT) AS rk, CAST(dense_rank() OVER (ORDER BY io DESC) AS INT) AS dr, round(percent_rank() OVER (ORDER BY io DESC), 6) AS pr, CAST(ntile(4) OVER w AS INT) AS nt FROM pdeg WINDOW w AS (ORDER BY io DESC, p)", m.PDEG),
    lambda s, d: m.graph.predicate_degree(m.edges(s, d)).select("p", F.row_number().over(_w()).alias("rn"), F.rank().over(W.orderBy(F.desc("io"))).alias("rk"), F.dense_rank().over(W.orderBy(F.desc("io"))).alias("dr"), F.round(F.percent_rank().over(W.orderBy(F.desc("io"))), 6).alias("pr"), F.ntile(4).over(_w()).alias("nt")),
)
_u = lambda: W.partitionBy("user_id").orderBy("ts", "event_id")
query("win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS behind FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", lambda s, d: load(s, d, "events").select("event_id", F.lag("event_id").over(_u()).alias("before"), F.lead("event_id").over(_u()).alias("behind")))
_o = lambda: W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
query("win_running_rows", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS total FROM orders", lambda s, d: load(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(_o().rowsBetween(W.unboundedPreceding, W.currentRow)), 2).alias("total")))
query("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY epoch(o_orderdate) RANGE BETWEEN 2592000 PRECEDING AND CURRENT ROW) AS n FROM orders", lambda s, d: load(s, d, "orders").withColumn("e", F.unix_seconds(C("o_orderdate").cast("timestamp"))).select("o_orderkey", F.count("*").over(W.partitionBy("o_custkey").orderBy("e").rangeBetween(-2592000, 0)).alias("n")))
_all = lambda: _o().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
query("win_first_last_nth", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS n FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", lambda s, d: load(s, d, "orders").select("o_orderkey", F.first("o_orderkey").over(_all()).alias("f"), F.last("o_orderkey").over(_all()).alias("l"), F.nth_value("o_orderkey", 2).over(_all()).alias("n")))
query("win_share_total", m.sql("SELECT topic, p, round(1.0 / count(*) OVER (PARTITION BY topic), 6) AS share FROM fixed", m.FIXED), lambda s, d: m.fixed(s, d).select("topic", "p", F.round(1 / F.count("*").over(W.partitionBy("topic")), 6).alias("share")))
query("sort_global", "SELECT p_partkey, CAST(row_number() OVER (ORDER BY p_retailprice DESC, p_partkey) AS INT) AS pos FROM part QUALIFY pos <= 50", lambda s, d: load(s, d, "part").orderBy(F.desc("p_retailprice"), "p_partkey").limit(50).select("p_partkey", F.row_number().over(W.orderBy(F.desc("p_retailprice"), "p_partkey")).alias("pos")))
query("sort_limit_offset", "SELECT p_partkey FROM part ORDER BY p_retailprice, p_partkey LIMIT 10 OFFSET 20", lambda s, d: load(s, d, "part").orderBy("p_retailprice", "p_partkey").offset(20).limit(10).select("p_partkey"))
query("sort_nulls", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id ORDER BY l.quality NULLS LAST, d.doc_id LIMIT 20", lambda s, d: load(s, d, "documents", ["doc_id"]).join(load(s, d, "labels"), "doc_id", "left").orderBy(F.asc_nulls_last("quality"), "doc_id").limit(20).select("doc_id"))
query("topk_per_group", "SELECT p_brand, p_partkey, CAST(row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS INT) AS rank FROM part QUALIFY rank <= 3", lambda s, d: relational.topk(load(s, d, "part", ["p_brand", "p_partkey", "p_retailprice"]), ["p_brand"], [F.desc("p_retailprice"), C("p_partkey")], 3).select("p_brand", "p_partkey", "rank"))
for _h, _q in (("union_distinct", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    query(f"set_{_h}", f"SELECT c_nationkey AS n FROM customer {_q} SELECT s_nationkey FROM supplier", lambda s, d, h=_h: relational.setop(load(s, d, "customer").select(C("c_nationkey").alias("n")), load(s, d, "supplier").select(C("s_nationkey").alias("n")), h))

# scalar functions -------------------------------------------------------------------------------------------------------------

query("fn_string", "SELECT p_partkey, upper(p_name) AS up, split_part(p_name, ' ', 1) AS first, lpad(CAST(p_size AS VARCHAR), 4, '0') AS pad, replace(p_type, 'E', 'e') AS rep, levenshtein(p_brand, 'Brand#11') AS dist, reverse(p_brand) AS back FROM part", lambda s, d: load(s, d, "part").select("p_partkey", F.upper("p_name").alias("up"), F.split_part("p_name", F.lit(" "), F.lit(1)).alias("first"), F.lpad(C("p_size").cast("string"), 4, "0").alias("pad"), F.replace("p_type", F.lit("E"), F.lit("e")).alias("rep"), F.levenshtein("p_brand", F.lit("Brand#11")).cast("long").alias("dist"), F.reverse("p_brand").alias("back")))
query("fn_local_name", "SELECT s, regexp_extract(s, '^(.*)[:/#][^:/#]*$', 1) AS ns, regexp_extract(s, '([^:/#]*)$', 1) AS local FROM (SELECT 'Nation:' || n_nationkey AS s FROM nation)", lambda s, d: build_facts(s, d, tables=("nation",)).select("s").distinct().select("s", text.namespace(C("s")).alias("ns"), text.local_name(C("s")).alias("local")))
query("fn_url", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path, regexp_extract(url, '\\?([^#]*)', 1) AS q FROM pages", lambda s, d: load(s, d, "pages", ["page_id", "url"]).select("page_id", text.url_host(C("url")).alias("host"), text.url_path(C("url")).alias("path"), text.url_query(C("url")).alias("q")))
query("fn_html_links", "SELECT page_id, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS n, nullif(regexp_extract(html, 'lang=\"([^\"]*)\"', 1), '') AS lang FROM pages", lambda s, d: load(s, d, "pages", ["page_id", "html"]).select("page_id", F.size(text.links(C("html"))).cast("long").alias("n"), text.page_language(C("html")).alias("lang")))
query("fn_tokens", "SELECT source, count(*) AS tokens, count(DISTINCT t) AS kinds FROM (SELECT source, unnest(regexp_split_to_array(lower(text), '[ \\t\\n]+')) AS t FROM documents) WHERE t <> '' GROUP BY 1", lambda s, d: load(s, d, "documents", ["source", "text"]).select("source", F.explode(text.tokens(C("text"))).alias("t")).groupBy("source").agg(F.count("*").alias("tokens"), F.count_distinct("t").alias("kinds")))
query("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS mon, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days, strftime(o_orderdate + INTERVAL 1 MONTH, '%Y-%m-%d') AS due FROM orders", lambda s, d: load(s, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.quarter("o_orderdate").cast("long").alias("q"), day(F.date_trunc("month", "o_orderdate")).alias("mon"), F.datediff("o_orderdate", F.lit("1992-01-01").cast("date")).cast("long").alias("days"), day(F.add_months("o_orderdate", 1)).alias("due")))
query("fn_math", "SELECT p_partkey, round(ln(p_retailprice), 6) AS ln, round(sqrt(p_size), 6) AS root, CAST(p_partkey % 7 AS BIGINT) AS m, floor(p_retailprice / 10) AS f, greatest(p_size, 25) AS g, round(power(p_size, 2), 2) AS sq FROM part", lambda s, d: load(s, d, "part").select("p_partkey", F.round(F.ln("p_retailprice"), 6).alias("ln"), F.round(F.sqrt("p_size"), 6).alias("root"), F.pmod("p_partkey", F.lit(7)).alias("m"), F.floor(C("p_retailprice") / 10).cast("double").alias("f"), F.greatest(C("p_size"), F.lit(25)).alias("g"), F.round(F.pow("p_size", F.lit(2)), 2).alias("sq")))
_cs = "cs AS (SELECT p, list_sort(list(concept)) AS cs FROM nbr GROUP BY p)"
query("fn_array", m.sql("SELECT a.p AS p1, b.p AS p2, array_to_string(list_sort(list_intersect(a.cs, b.cs)), ',') AS both, array_to_string(list_sort(list_distinct(a.cs || b.cs)), ',') AS every FROM cs a JOIN cs b ON a.p < b.p AND list_has_any(a.cs, b.cs)", m.INC, m.NBR, _cs), lambda s, d: (lambda a: a.select(C("p").alias("p1"), C("cs").alias("x")).join(a.select(C("p").alias("p2"), C("cs").alias("y")), (C("p1") < C("p2")) & F.arrays_overlap("x", "y")).select("p1", "p2", F.concat_ws(",", F.array_sort(F.array_intersect("x", "y"))).alias("both"), F.concat_ws(",", F.array_sort(F.array_union("x", "y"))).alias("every")))(udfs.arrays(neighbourhood(m.edges(s, d)))))
query("fn_array_hof", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS sq, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings", lambda s, d: load(s, d, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 5).alias("sq"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos")))
query("fn_map", "SELECT n_nationkey, CASE n_regionkey WHEN 0 THEN 'a' WHEN 1 THEN 'b' END AS code, 2 AS size FROM nation", lambda s, d: load(s, d, "nation").withColumn("mp", F.create_map(F.lit(0), F.lit("a"), F.lit(1), F.lit("b"))).select("n_nationkey", F.try_element_at("mp", C("n_regionkey")).alias("code"), F.size(F.map_keys("mp")).alias("size")))
query("fn_struct", "SELECT n_nationkey, n_name || '/' || n_regionkey AS told FROM nation", lambda s, d: load(s, d, "nation").withColumn("st", F.struct("n_name", "n_regionkey")).select("n_nationkey", F.concat_ws("/", "st.n_name", C("st.n_regionkey").cast("string")).alias("told")))
query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events", lambda s, d: load(s, d, "events", ["event_id", "props"]).select("event_id", F.from_json("props", "k int")["k"].alias("k")))
query("fn_variant", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events", lambda s, d: load(s, d, "events", ["event_id", "props"]).select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")))
query("fn_vector_cosine", "SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 5) AS cos FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id < b.vec_id", lambda s, d: vectors.pair_cosines(load(s, d, "embeddings").select("label", C("vec_id").alias("id"), C("embedding").alias("v")), "label"))
query("fn_vector_nearest", "SELECT label, a, CAST(row_number() OVER (PARTITION BY label, a ORDER BY cos DESC, b) AS INT) AS rank, b, round(cos, 5) AS cos FROM (SELECT x.label, x.vec_id AS a, y.vec_id AS b, list_cosine_similarity(CAST(x.embedding AS DOUBLE[]), CAST(y.embedding AS DOUBLE[])) AS cos FROM embeddings x JOIN embeddings y ON x.label = y.label AND x.vec_id <> y.vec_id) QUALIFY rank <= 5", lambda s, d: relational.topk(vectors.nearest(load(s, d, "embeddings").select("label", C("vec_id").alias("id"), C("embedding").alias("v")), "label", 5), ["label", "a"], [F.desc("cos"), C("b")], 5).select("label", "a", "rank", "b", F.round("cos", 5).alias("cos")))
query("fn_conditional", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band, nullif(o_orderstatus, 'P') AS status FROM orders", lambda s, d: load(s, d, "orders").select("o_orderkey", F.when(C("o_totalprice") > 200000, "high").when(C("o_totalprice") > 100000, "mid").otherwise("low").alias("band"), F.nullif("o_orderstatus", F.lit("P")).alias("status")))

# sub-queries, samples, functions of the user ------------------------------------------------------------------------------------

_SUB = {
    "sub_scalar": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)",
    "sub_exists": "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'P')",
    "sub_in": "SELECT s_suppkey FROM supplier WHERE s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)",
    "sub_correlated": "SELECT o_orderkey FROM orders a WHERE o_totalprice = (SELECT max(o_totalprice) FROM orders b WHERE b.o_custkey = a.o_custkey)",
}
for _n, _q in _SUB.items():
    query(_n, _q, lambda s, d, q=_q: (tables.register(s, d), s.sql(q))[1])
query("sample_seeded", "SELECT doc_id FROM documents WHERE substr(md5(CAST(doc_id AS VARCHAR) || '/5'), 1, 8) < '19999999'", lambda s, d: relational.sample_hash(load(s, d, "documents", ["doc_id"]), "doc_id", 0.1, 5))
_PAIRS = m.sql("SELECT p1, p2, round(share, 6) AS share FROM share WHERE p1 < p2", *m.GRAPH)


def _pairs(s: SparkSession, d: str) -> DataFrame:
    a = udfs.arrays(neighbourhood(m.edges(s, d)))
    return a.select(C("p").alias("p1"), C("cs").alias("x")).join(a.select(C("p").alias("p2"), C("cs").alias("y")), (C("p1") < C("p2")) & F.arrays_overlap("x", "y"))


query("udf_scalar_arrow", _PAIRS, lambda s, d: m.rounded(_pairs(s, d).select("p1", "p2", udfs.share_udf("x", "y").alias("share"))))
query("udaf_grouped", m.sql("SELECT p1, round(avg(sm), 6) AS mean FROM sm GROUP BY 1", *m.FULL), lambda s, d: m.rounded(m.matrix(s, d).groupBy("p1").agg(udfs.mean_udaf("sm").alias("mean"))))
query("udtf_walk", "SELECT unnest([1, 2, 3]) AS step, unnest(['lang', 'text', 'role']) AS p", lambda s, d: (udfs.register(s), s.sql("SELECT * FROM walk_steps('lang>text>role')"))[1])
query("udf_sql", _PAIRS, lambda s, d: (udfs.register(s), m.similarity.share_scores(neighbourhood(m.edges(s, d))).createOrReplaceTempView("pairs_of"), s.sql("SELECT p1, p2, round(share_of(n12, n1, n2), 6) AS share FROM pairs_of"))[2])
query("map_in_pandas", m.sql("SELECT p1, round(sum(x * x), 6) AS norm FROM dense GROUP BY 1", *m.FULL, m.DENSE), lambda s, d: m.rounded(udfs.row_norms(m.features(s, d).select(C("p").alias("p1"), C("features").alias("values")))))
query("apply_in_pandas", m.sql("SELECT p1, p2, round(sm - avg(sm) OVER (PARTITION BY p1), 6) AS centred FROM sm", *m.FULL), lambda s, d: m.rounded(udfs.centred(m.matrix(s, d).select("p1", "p2", "sm"))))
query("cogroup_pandas", m.sql("SELECT c.p1, count(*) AS rows, (SELECT round(max(sm), 6) FROM sm WHERE sm.p1 = c.p1 AND sm.p1 <> sm.p2) AS best FROM chain c GROUP BY 1", *m.FULL), lambda s, d: m.rounded(udfs.matched(m.chain(s, d).select("p1", "p2"), m.matrix(s, d).where("p1 <> p2").select("p1", "sm"))))
query("brand_spanning_tree", None, lambda s, d: baselines.spanning_tree(m.similarity.share_scores(brand_links(s, d)).select("p1", "p2", (1 - C("share")).alias("d"))))
query("brand_theta_error", None, lambda s, d: sketches.share_error(brand_links(s, d), sketches.share_scores_theta(brand_links(s, d))))
query("contract_same", "SELECT 'Nation:' || n_nationkey AS term, 'Nation:' || min(CAST(n_nationkey AS VARCHAR)) OVER (PARTITION BY n_regionkey) AS name FROM nation", lambda s, d: normalise.contract_same(load(s, d, "nation").withColumn("first", F.min(C("n_nationkey").cast("string")).over(W.partitionBy("n_regionkey"))).select(F.concat(F.lit("Nation:"), C("n_nationkey").cast("string")).alias("a"), F.concat(F.lit("Nation:"), "first").alias("b"))))
query("link_terms", "SELECT a.vec_id AS id1, b.vec_id AS id2 FROM embeddings a, embeddings b WHERE list_distance(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) <= 0.9", lambda s, d: normalise.link_terms(load(s, d, "embeddings").select(C("vec_id").alias("id"), C("embedding").alias("v")), load(s, d, "embeddings").select(C("vec_id").alias("id"), C("embedding").alias("v")), 0.9).select("id1", "id2"))
