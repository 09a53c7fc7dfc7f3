"""Facts from tables by mapping rules, and the schema graph that they induce.

A rule says which concept a table's rows are, how a row is named, and for each predicate which column gives the object and
of which concept that is. Columns that sort rows into kinds give subclasses. Facts come from one scan of each table; the
schema graph is aggregated before classes are spread out, so only a handful of rows cross the shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..settle import settle
from ..sources.tables import load_table, stamp


@dataclass(frozen=True)
class Rule:
    """One table. id: SQL for a row's name; links: predicate -> (concept, SQL of the object); kind: SQL of the subclass; far: predicate -> (table, key there, key here, SQL of the object's subclass); many: predicates whose SQL is an array."""

    table: str
    concept: str
    ns: str
    id: str
    links: dict[str, tuple[str, str]]
    kind: str | None = None
    far: dict[str, tuple[str, str, str, str]] = field(default_factory=dict)
    many: tuple[str, ...] = ()


LINE_ID = "xxhash64(l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate)"
RULES = (
    Rule("region", "Region", "sales", "r_regionkey", {"name": ("Name", "r_name")}),
    Rule("nation", "Nation", "sales", "n_nationkey", {"name": ("Name", "n_name"), "region": ("Region", "n_regionkey")}),
    Rule("customer", "Customer", "sales", "c_custkey", {"name": ("Name", "c_name"), "nation": ("Nation", "c_nationkey"), "acctbal": ("Money", "c_acctbal"), "mktsegment": ("Segment", "c_mktsegment")}, "c_mktsegment"),
    Rule("supplier", "Supplier", "sales", "s_suppkey", {"name": ("Name", "s_name"), "nation": ("Nation", "s_nationkey"), "acctbal": ("Money", "s_acctbal")}),
    Rule("part", "Part", "sales", "p_partkey", {"name": ("Name", "p_name"), "brand": ("Brand", "p_brand"), "type": ("PartType", "p_type"), "size": ("Size", "p_size"), "retailprice": ("Money", "p_retailprice")}, "p_type"),
    Rule("orders", "Order", "sales", "o_orderkey", {"customer": ("Customer", "o_custkey"), "orderstatus": ("Status", "o_orderstatus"), "totalprice": ("Money", "o_totalprice"), "orderdate": ("Date", "o_orderdate"), "orderpriority": ("Priority", "o_orderpriority")}, "o_orderstatus", {"customer": ("customer", "c_custkey", "o_custkey", "c_mktsegment")}),
    Rule(
        "lineitem", "Line", "sales", LINE_ID,
        {"order": ("Order", "l_orderkey"), "part": ("Part", "l_partkey"), "supplier": ("Supplier", "l_suppkey"), "linenumber": ("Ordinal", "l_linenumber"), "quantity": ("Quantity", "l_quantity"), "extendedprice": ("Money", "l_extendedprice"), "discount": ("Rate", "l_discount"), "tax": ("Rate", "l_tax"), "returnflag": ("ReturnFlag", "l_returnflag"), "linestatus": ("Status", "l_linestatus"), "shipdate": ("Date", "l_shipdate")},
        "l_returnflag", {"order": ("orders", "o_orderkey", "l_orderkey", "o_orderstatus"), "part": ("part", "p_partkey", "l_partkey", "p_type")},
    ),
    Rule("events", "Event", "stream", "event_id", {"ts": ("Timestamp", "ts"), "user": ("User", "user_id"), "event_type": ("EventKind", "event_type"), "value": ("Score", "value"), "props": ("Json", "props")}, "event_type"),
    Rule("documents", "Document", "text", "doc_id", {"text": ("Text", "text"), "lang": ("Lang", "lang"), "source": ("Source", "source"), "n_chars": ("Count", "n_chars")}, "lang"),
    Rule("labels", "Document", "text", "doc_id", {"quality": ("Judgement", "quality"), "toxic": ("Judgement", "toxic")}, None, {"*": ("documents", "doc_id", "doc_id", "lang")}),
    Rule("benchmark", "Bench", "text", "item_id", {"text": ("Text", "text")}),
    Rule("embeddings", "Vec", "vec", "vec_id", {"embedding": ("Vector", "to_json(embedding)"), "label": ("ClassLabel", "label")}),
    Rule("pages", "Page", "web", "page_id", {"url": ("Url", "url"), "html": ("Html", "html"), "lang": ("Lang", "nullif(regexp_extract(html, 'lang=\"([^\"]*)\"', 1), '')"), "host": ("Host", "regexp_extract(url, '^[a-z]+://([^/]+)', 1)"), "link": ("Path", "regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")}, "nullif(regexp_extract(html, 'lang=\"([^\"]*)\"', 1), '')", {}, ("link",)),
    Rule("conversations", "Turn", "chat", "concat(conv_id, '/', turn)", {"conv": ("Conversation", "conv_id"), "turn": ("Ordinal", "turn"), "role": ("Role", "role"), "text": ("Text", "text")}, "role"),
)
#: Columns that are there exactly if the SQL of an object is.
PRESENT = {"to_json(embedding)": "embedding"}
#: Predicates of the fact model itself, which no topic needs.
BUILTINS = ("is_a", "same_as", "see_also")
UNIVERSAL = "Thing"


def build_facts(spark: SparkSession, sf_dir: str, rules: tuple[Rule, ...] = RULES, tables: tuple[str, ...] | None = None) -> DataFrame:
    """(s, p, o, s_class, s_sub, o_class, o_sub, ns): one scan a table; a null object gives no fact."""
    parts = []
    for r in rules:
        if tables and r.table not in tables:
            continue
        df = load_table(spark, sf_dir, r.table)
        subs: dict[str, str] = {}
        kind = F.expr(r.kind).cast("string") if r.kind else F.lit(None).cast("string")
        for n, (p, (far, there, here, sub)) in enumerate(r.far.items()):
            side = load_table(spark, sf_dir, far, [there, sub]).select(F.col(there).alias(f"__k{n}"), F.col(sub).alias(f"__v{n}"))
            df = df.join(side, F.col(here) == F.col(f"__k{n}"), "inner" if p == "*" else "left")
            if p == "*":
                kind = F.col(f"__v{n}")
            else:
                subs[p] = f"__v{n}"
        one = []
        for p, (concept, sql) in r.links.items():
            values = F.expr(sql).cast("array<string>") if p in r.many else F.array(F.expr(sql).cast("string"))
            sub = F.col(subs[p]) if p in subs else F.lit(None).cast("string")
            one.append(_linked(values, p, concept, sub))
        name = F.concat(F.lit(r.concept + ":"), F.expr(r.id).cast("string"))
        rows = df.select(name.alias("s"), F.lit(r.concept).alias("s_class"), kind.alias("s_sub"), F.lit(r.ns).alias("ns"), F.explode(F.concat(*one)).alias("l"))
        named = F.when(F.col("l.o_class").isin(*_subjects(rules)), F.concat("l.o_class", F.lit(":"), "l.o")).otherwise(F.col("l.o"))
        parts.append(rows.where("l.o is not null").select("s", F.col("l.p").alias("p"), named.alias("o"), "s_class", "s_sub", F.col("l.o_class").alias("o_class"), F.col("l.o_sub").alias("o_sub"), "ns"))
    return reduce(DataFrame.unionByName, parts)


def fact_kinds(spark: SparkSession, sf_dir: str, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(p, s_class, s_sub, o_class, o_sub, ns, n): how many facts of each kind, counted in columns of the tables without making a fact."""
    parts = []
    for r in rules:
        df = load_table(spark, sf_dir, r.table)
        kind, keys, subs = (F.expr(r.kind).cast("string") if r.kind else F.lit(None).cast("string")), [], {}
        for n, (p, (far, there, here, sub)) in enumerate(r.far.items()):
            side = load_table(spark, sf_dir, far, [there, sub]).select(F.col(there).alias(f"__k{n}"), F.col(sub).alias(f"__v{n}"))
            df = df.join(side, F.col(here) == F.col(f"__k{n}"), "inner" if p == "*" else "left")
            if p == "*":
                kind = F.col(f"__v{n}")
            else:
                subs[p] = f"__v{n}"
                keys.append(F.col(f"__v{n}"))
        count = {p: F.coalesce(F.sum(F.size(F.expr(q))), F.lit(0)) if p in r.many else F.count(F.expr(PRESENT.get(q, q))) for p, (_, q) in r.links.items()}
        wide = df.groupBy(kind.alias("s_sub"), *keys).agg(*[c.cast("long").alias(f"__n_{p}") for p, c in count.items()])
        none = F.lit(None).cast("string")
        each = F.array(*[F.struct(F.lit(p).alias("p"), F.lit(o).alias("o_class"), (F.col(subs[p]) if p in subs else none).alias("o_sub"), F.col(f"__n_{p}").alias("n")) for p, (o, _) in r.links.items()])
        rows = wide.select("s_sub", F.explode(each).alias("l"))
        parts.append(rows.where("l.n > 0").select("l.p", F.lit(r.concept).alias("s_class"), "s_sub", "l.o_class", "l.o_sub", F.lit(r.ns).alias("ns"), "l.n"))
    return reduce(DataFrame.unionByName, parts)


def _subjects(rules: tuple[Rule, ...]) -> list[str]:
    return sorted({r.concept for r in rules})


def _linked(values, p: str, concept: str, sub):  # noqa: ANN001, ANN202
    return F.transform(values, lambda o: F.struct(F.lit(p).alias("p"), o.alias("o"), F.lit(concept).alias("o_class"), sub.alias("o_sub")))


def type_terms(facts: DataFrame, refine: bool = False, include_root: bool = False) -> DataFrame:
    """Facts with sc and oc, the classes of subject and object: the concept, and with ``refine`` its subclass, and with ``include_root`` the universal one."""
    extra = F.array(F.lit(UNIVERSAL)) if include_root else F.array().cast("array<string>")
    both = lambda c, s: F.concat(F.array(c), F.when(F.col(s).isNotNull(), F.array(F.concat_ws("/", c, s))).otherwise(F.array().cast("array<string>"))) if refine else F.array(c)
    spread = facts.withColumn("__sc", F.concat(both("s_class", "s_sub"), extra)).withColumn("__oc", both("o_class", "o_sub"))
    return spread.withColumn("sc", F.explode("__sc")).withColumn("oc", F.explode("__oc")).drop("__sc", "__oc")


def induce_schema(facts: DataFrame, refine: bool = False, include_root: bool = False) -> DataFrame:
    """(sc, p, oc, ns, n_facts): counted by kind of fact first, then spread over classes."""
    kinds = facts.groupBy("p", "s_class", "s_sub", "o_class", "o_sub", "ns").agg(F.count("*").alias("n"))
    return type_terms(kinds, refine, include_root).groupBy("sc", "p", "oc").agg(F.min("ns").alias("ns"), F.sum("n").alias("n_facts"))


def domain_predicates(edges: DataFrame, builtins: tuple[str, ...] = BUILTINS) -> DataFrame:
    return edges.where(~F.col("p").isin(*builtins))


def incidence(edges: DataFrame) -> DataFrame:
    """(p, concept, side): distinct links, by the side they are on."""
    into = edges.select("p", F.col("sc").alias("concept"), F.lit("in").alias("side"))
    return into.unionAll(edges.select("p", F.col("oc").alias("concept"), F.lit("out").alias("side"))).distinct()


def neighbourhood(edges: DataFrame) -> DataFrame:
    """(p, concept): what a predicate touches, whatever the direction."""
    return edges.select("p", F.explode(F.array("sc", "oc")).alias("concept")).distinct()


def instance_neighbourhood(facts: DataFrame) -> DataFrame:
    """(p, concept) over the facts' own subjects and objects."""
    return facts.select("p", F.explode(F.array("s", "o")).alias("concept")).distinct()


def schema_of_kinds(kinds: DataFrame, refine: bool = False, include_root: bool = False) -> DataFrame:
    """The schema graph from counts of kinds; the same as from facts."""
    return type_terms(kinds, refine, include_root).groupBy("sc", "p", "oc").agg(F.min("ns").alias("ns"), F.sum("n").alias("n_facts"))


_SCHEMAS: dict[tuple, DataFrame] = {}


def forget() -> None:
    """Drop the schema graphs that the session has made."""
    _SCHEMAS.clear()


def schema(spark: SparkSession, sf_dir: str, kind: str = "base") -> DataFrame:
    """The schema graph of the given tables: base, refined (with subclasses) or rooted (with the universal concept); made once a session and state of the tables."""
    key = (spark.sparkContext.applicationId, sf_dir, stamp(spark, sf_dir), kind)
    if key not in _SCHEMAS:
        _SCHEMAS[key] = settle(schema_of_kinds(fact_kinds(spark, sf_dir), kind == "refined", kind == "rooted"))
    return _SCHEMAS[key]


#: DuckDB spelling of the rules' SQL where it differs.
DIALECT = {LINE_ID: "0", "to_json(embedding)": "'x'", "nullif(regexp_extract(html, 'lang=\"([^\"]*)\"', 1), '')": "nullif(regexp_extract(html, 'lang=\"([^\"]*)\"', 1), '')", "concat(conv_id, '/', turn)": "concat(conv_id, '/', turn)"}


def schema_sql(kind: str = "base", rules: tuple[Rule, ...] = RULES) -> str:
    """SELECT of (sc, p, oc, ns, n_facts) for DuckDB over the raw tables."""
    parts = []
    for r in rules:
        for p, (concept, sql) in r.links.items():
            sql, source, sub, kinds = DIALECT.get(sql, sql), r.table, None, DIALECT.get(r.kind, r.kind)
            if p in r.far or "*" in r.far:
                far, there, here, value = r.far.get(p) or r.far["*"]
                source = f"{r.table} a {'JOIN' if '*' in r.far else 'LEFT JOIN'} {far} b ON a.{here} = b.{there}"
                sub = f"b.{value}" if p in r.far else None
                kinds = f"b.{value}" if "*" in r.far else kinds
            value = f"unnest({sql})" if p in r.many else sql
            prefix = "a." if source != r.table and sql.isidentifier() else ""
            inner = f"SELECT {prefix}{value} AS o, CAST({kinds or 'NULL'} AS VARCHAR) AS k, CAST({sub or 'NULL'} AS VARCHAR) AS f FROM {source}"
            sc, oc = [f"'{r.concept}'"], [f"'{concept}'"]
            if kind == "refined" and kinds:
                sc.append(f"'{r.concept}/' || k")
            if kind == "rooted":
                sc.append(f"'{UNIVERSAL}'")
            if kind == "refined" and sub:
                oc.append(f"'{concept}/' || f")
            for x in sc:
                for y in oc:
                    parts.append(f"SELECT {x} AS sc, '{p}' AS p, {y} AS oc, '{r.ns}' AS ns, count(*) AS n FROM ({inner}) WHERE o IS NOT NULL AND {x} IS NOT NULL AND {y} IS NOT NULL GROUP BY 1, 2, 3, 4")
    return "SELECT sc, p, oc, min(ns) AS ns, CAST(sum(n) AS BIGINT) AS n_facts FROM (" + " UNION ALL ".join(parts) + ") GROUP BY sc, p, oc"
