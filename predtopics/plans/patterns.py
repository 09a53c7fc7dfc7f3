"""Query graphs as patterns, their rewrites, and their evaluation as joins."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce
from operator import mul

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..settle import settle, small

#: Pairs of a product in a task, of bindings that stand for others.
PAIRS = 500_000


@dataclass(frozen=True)
class Pattern:
    """subject and object: ?variables or constants; p: a predicate. Patterns of one optional group are met together or not at all; 0 is required."""

    s: str
    p: str
    o: str
    optional: int = 0

    def variables(self) -> tuple[str, ...]:
        return tuple(x for x in (self.s, self.o) if x.startswith("?"))


@dataclass(frozen=True)
class Filter:
    """left op right, of variables or constants; op one of = != < <= > >=."""

    left: str
    op: str
    right: str

    def variables(self) -> set[str]:
        return {x for x in (self.left, self.right) if x.startswith("?")}


@dataclass(frozen=True)
class QueryGraph:
    select: tuple[str, ...]
    patterns: tuple[Pattern, ...]
    types: tuple[tuple[str, str], ...] = ()  # (variable, concept)
    filters: tuple[Filter, ...] = ()
    distinct: bool = True
    order: tuple[str, ...] = ()  # ?variable, or -?variable for falling order
    limit: int | None = None
    count: str | None = field(default=None)  # alias of count(*), instead of rows


def prune_optional(q: QueryGraph) -> QueryGraph:
    """Leave out optional groups that bind no variable anew: under distinct they change no answer."""
    if not q.distinct:
        return q
    bound = {v for x in q.patterns if not x.optional for v in x.variables()} | {v for v, _ in q.types}
    keep: list[Pattern] = [x for x in q.patterns if not x.optional]
    for g in sorted({x.optional for x in q.patterns if x.optional}):
        group = [x for x in q.patterns if x.optional == g]
        new = {v for x in group for v in x.variables()} - bound
        if new:
            keep += group
            bound |= new
    return replace(q, patterns=tuple(keep))


def order_patterns(q: QueryGraph, sizes: dict[str, int]) -> QueryGraph:
    """Required patterns smallest first, each joined to what is bound as long as one is; optional ones stay behind."""
    rest = [x for x in q.patterns if not x.optional]
    out: list[Pattern] = []
    bound: set[str] = set()
    while rest:
        linked = [x for x in rest if set(x.variables()) & bound] or rest
        best = min(linked, key=lambda x: (-len(set(x.variables()) & bound), sizes.get(x.p, 1 << 60), x.s, x.p, x.o))
        rest.remove(best)
        out.append(best)
        bound |= set(best.variables())
    return replace(q, patterns=(*out, *(x for x in q.patterns if x.optional)))


def crosses(q: QueryGraph) -> bool:
    """Whether the required patterns fall into parts without a common variable."""
    groups: list[set[str]] = []
    for x in [set(p.variables()) for p in q.patterns if not p.optional] + [{v} for v, _ in q.types]:
        touching = [g for g in groups if g & x]
        groups = [g for g in groups if not g & x] + [set().union(x, *touching)]
    return len(groups) > 1


def _scan(facts: DataFrame, x: Pattern) -> DataFrame:
    """Bindings of one pattern: a scan of one predicate."""
    rows = facts.where(F.col("p") == x.p)
    rows = rows if x.s.startswith("?") else rows.where(F.col("s") == x.s)
    rows = rows if x.o.startswith("?") else rows.where(F.col("o") == x.o)
    if x.s == x.o and x.s.startswith("?"):
        rows = rows.where(F.col("s") == F.col("o"))
    columns = [F.col(side).alias(name[1:]) for side, name in (("s", x.s), ("o", x.o)) if name.startswith("?")]
    return rows.select(*(columns[:1] if x.s == x.o else columns or [F.lit(1).alias("__hit")]))


def _join(left: DataFrame | None, right: DataFrame, how: str = "inner") -> DataFrame:
    if left is None:
        return right
    on = [c for c in right.columns if c in left.columns and c != "__hit"]
    right = right.drop("__hit")
    if not on:
        return left.crossJoin(right) if how == "inner" else left.join(right, F.lit(True), how)
    return left.join(right, on, how)


def _term(x: str) -> Column:
    return F.col(x[1:]) if x.startswith("?") else F.lit(x)


def _condition(f: Filter) -> Column:
    a, b = _term(f.left), _term(f.right)
    if not (f.left.startswith("?") and f.right.startswith("?")) and f.op not in ("=", "!="):
        a, b = a.cast("double"), b.cast("double")
    return {"=": a == b, "!=": a != b, "<": a < b, "<=": a <= b, ">": a > b, ">=": a >= b}[f.op]


def functional(facts: DataFrame, q: QueryGraph) -> frozenset[str]:
    """Predicates of the query of which no subject has a second fact, repeats included: one aggregation of the facts."""
    seen = facts.where(F.col("p").isin(*{x.p for x in q.patterns})).groupBy("s", "p").agg(F.count("*").alias("n")).groupBy("p").agg(F.max("n").alias("n"))
    return frozenset(r["p"] for r in seen.where("n = 1").collect())


def _star(facts: DataFrame, group: list[Pattern]) -> DataFrame:
    """Bindings of functional patterns of one subject: one grouping instead of a join each."""
    preds, s = sorted({x.p for x in group}), group[0].s
    rows = facts.where(F.col("p").isin(*preds))
    rows = rows.groupBy("s").agg(*[F.max(F.when(F.col("p") == p, F.col("o"))).alias(f"__{n}") for n, p in enumerate(preds)])
    rows = rows.where(F.forall(F.array(*[f"__{n}" for n in range(len(preds))]), lambda o: o.isNotNull()))
    at = {s: F.col("s")}
    for x in group:
        o = F.col(f"__{preds.index(x.p)}")
        if x.o in at or not x.o.startswith("?"):
            rows = rows.where(o == at.get(x.o, F.lit(x.o)))
        else:
            at[x.o] = o
    rows = rows if s.startswith("?") else rows.where(F.col("s") == s)
    return rows.select(*[c.alias(v[1:]) for v, c in at.items() if v.startswith("?")], *([] if len(at) > 1 or s.startswith("?") else [F.lit(1).alias("__hit")]))


def _told(q: QueryGraph, single: frozenset[str]) -> bool:
    """Whether what is selected tells all other variables, by functional predicates: then no two bindings give one answer.

    Optional groups without a variable of their own are left aside: their bindings are distinct, so they make no second one.
    """
    must = [x for x in q.patterns if not x.optional]
    bound = {v for x in must for v in x.variables()} | {v for v, _ in q.types}
    if any(x.p not in single for x in must) or not q.distinct or not bound >= {v for x in q.patterns for v in x.variables()}:
        return False
    known = set(q.select)
    while more := {x.o for x in must if x.o.startswith("?") and x.o not in known and (x.s in known or not x.s.startswith("?"))}:
        known |= more
    return known >= bound


def _foldable(q: QueryGraph, v: str) -> None:
    mine = [x for x in q.patterns if v in x.variables()]
    if not q.distinct or q.count or q.limit is not None:
        raise ValueError("only distinct answers, all of them, can be folded")
    if v not in q.select or v in {w for f in q.filters for w in f.variables()} or any(x.s != v or x.o == v for x in mine) or not (any(not x.optional for x in mine) or v in {w for w, _ in q.types}):
        raise ValueError("only a selected variable that is required or has a class, is nothing but a subject and has no filter can be folded")


def alike(facts: DataFrame, q: QueryGraph, v: str, types: DataFrame | None = None) -> DataFrame:
    """(v, __n): one of the subjects that have the same facts of the query's predicates for v and the same of its classes, and their number.

    They give the same answers but for their names, so that one stands for all; whether predicates are functional does not matter.
    """
    _foldable(q, v)
    mine, concepts = [x for x in q.patterns if v in x.variables()], sorted({c for w, c in q.types if w == v})
    linked = F.col("p").isin(*sorted({x.p for x in mine}))
    rows = facts.select("s", F.when(linked, F.struct("p", "o")).alias("__link"), (F.col("s_class") if concepts and types is None else F.lit(None).cast("string")).alias("__class"))
    if concepts and types is not None:
        rows = rows.unionByName(types.select("s", F.lit(None).cast(rows.schema["__link"].dataType).alias("__link"), F.col("class").alias("__class")))
    rows = rows.withColumn("__class", F.when(F.col("__class").isin(*concepts), F.col("__class"))).where("__link is not null or __class is not null")
    one = rows.groupBy("s").agg(*[F.sort_array(F.collect_set(c)).alias(c) for c in ("__link", "__class")])
    return one.groupBy("__link", "__class").agg(F.min("s").alias(v[1:]), F.count("*").alias("__n")).select(v[1:], "__n")


def evaluate(facts: DataFrame, q: QueryGraph, types: DataFrame | None = None, allow_cross: bool = False, single: frozenset[str] = frozenset(), fold: str | dict[str, DataFrame] | None = None) -> DataFrame:
    """Answers of a query graph over facts (s, p, o); types: (s, class) rows, else the facts' own s_class.

    Each pattern is one filtered scan; required ones are joined in order, filters apply as soon as their variables are bound,
    optional groups are left joins. A variable that an optional group leaves open cannot be joined on by a later group.
    single: predicates that are functional in these facts. Required patterns of them are one scan a subject, and where
    the selected variables tell all others through them, no answer is made twice and none is compared.
    fold: a variable, of whose bindings one stands for all that answer alike (see alike), or what alike gives of each of several
    variables, written, of this query or of one with more patterns; answers have __n, the number of answers that each stands for.
    """
    if crosses(q) and not allow_cross:
        raise ValueError("the patterns fall into parts without a common variable; allow_cross=True takes their product")
    fold = {fold: settle(alike(facts, q, fold, types))} if isinstance(fold, str) else fold or {}
    for v in fold:
        _foldable(q, v)
    ones = {v[1:]: small(df.withColumnRenamed("__n", f"__n_{v[1:]}")) for v, df in fold.items()}
    out, todo = None, list(q.filters)

    def filtered(df: DataFrame) -> DataFrame:
        for f in [f for f in todo if {v[1:] for v in f.variables()} <= set(df.columns)]:
            df = df.where(_condition(f))
            todo.remove(f)
        return df

    def folded(df: DataFrame) -> DataFrame:
        """Rows of the bindings that stand for others, with their number where it is not there yet."""
        for v in [v for v in ones if v in df.columns]:
            df = df.join(ones[v].select(v) if out is not None and v in out.columns else ones[v], v)
        return df

    def met(df: DataFrame) -> DataFrame:
        """Joined to what is there. A product of what stands for others is of few bytes, so it is written and dealt to tasks by its pairs instead."""
        keys = [v for v in ones if out is not None and v in out.columns]
        if not keys or set(df.columns) & set(out.columns):
            return _join(out, df)
        left, right = settle(out), settle(df)
        return _join(left.repartition(max(1, -(-left.count() * right.count() // PAIRS)), *keys), small(right))

    required: dict[object, list[Pattern]] = {}
    for n, x in enumerate(x for x in q.patterns if not x.optional):
        required.setdefault(x.s if x.p in single else n, []).append(x)
    for group in required.values():
        scan = _star(facts, group) if group[0].p in single else _scan(facts, group[0])
        out = met(filtered(folded(scan)))
    for v, concept in q.types:
        rows = types.where(F.col("class") == concept).select(F.col("s").alias(v[1:])) if types is not None else facts.where(F.col("s_class") == concept).select(F.col("s").alias(v[1:]))
        out = out.join(rows, v[1:], "left_semi") if out is not None and v[1:] in out.columns else met(folded(rows).distinct())
    sure = set(out.columns) if out is not None else set()
    opened: set[str] = set()
    for g in sorted({x.optional for x in q.patterns if x.optional}):
        group = [x for x in q.patterns if x.optional == g]
        names = {v[1:] for x in group for v in x.variables()}
        if names & opened:
            raise ValueError("an optional group joins on a variable that another one may leave open")
        side = None
        for x in group:
            side = _join(side, _scan(facts, x))
        side = side.distinct() if q.distinct else side
        out = _join(out, small(settle(folded(side))) if ones else side, "left")
        opened |= names - sure
    out = filtered(out)
    if q.count:
        return out.agg(F.count("*").alias(q.count))
    out = out.select(*[v[1:] for v in q.select], *([reduce(mul, [F.col(f"__n_{v}") for v in ones]).alias("__n")] if ones else []))
    out = out.distinct() if q.distinct and not _told(q, single) else out
    out = out.orderBy(*[F.desc(v[2:]) if v[0] == "-" else F.col(v[1:]) for v in q.order]) if q.order else out
    return out.limit(q.limit) if q.limit is not None else out


def counted(facts: DataFrame, q: QueryGraph, keys: list[str], name: str = "relations", types: DataFrame | None = None) -> DataFrame:
    """(keys, name): how many answers of a query, in which all variables are selected, there are for each binding of the keys.

    No answer is made: other variables are summed out one at a time, so joins have a row for each binding of what is left, with the
    number of answers it stands for. Parts without a common variable multiply.
    """
    every = {v[1:] for x in q.patterns for v in x.variables()} | {v[1:] for v, _ in q.types}
    if q.filters or q.count or q.limit is not None or any(x.optional for x in q.patterns) or not (q.distinct and every == {v[1:] for v in q.select}):
        raise ValueError("only required patterns with all variables selected can be counted without their answers")
    held = [_scan(facts, x).drop("__hit").distinct() if x.variables() else _scan(facts, x).limit(1).select() for x in q.patterns]
    for v, concept in q.types:
        rows = types.where(F.col("class") == concept) if types is not None else facts.where(F.col("s_class") == concept)
        held.append(rows.select(F.col("s").alias(v[1:])).distinct())
    held = [df.withColumn("__n", F.lit(1).cast("long")) for df in held]

    def product(some: list[DataFrame]) -> DataFrame:
        out, rest = some[0], list(some[1:])
        while rest:
            right = next((r for r in rest if set(r.columns) & set(out.columns) - {"__n"}), rest[0])
            rest = [r for r in rest if r is not right]
            right = right.withColumnRenamed("__n", "__m")
            on = [c for c in right.columns if c in out.columns]
            out = (out.join(right, on) if on else out.crossJoin(right)).withColumn("__n", F.col("__n") * F.col("__m")).drop("__m")
        return out

    open_ = every - set(keys)
    while open_:
        wide = {v: set().union(*[set(df.columns) for df in held if v in df.columns]) for v in open_}
        v = min(open_, key=lambda v: (len(wide[v]), v))
        made = product([df for df in held if v in df.columns])
        left = [c for c in made.columns if c not in (v, "__n")]
        held = [df for df in held if v not in df.columns] + [made.groupBy(*left).agg(F.sum("__n").alias("__n")).where("__n > 0")]
        open_.remove(v)
    return product(sorted(held, key=lambda df: len(df.columns) == 1)).select(*keys, F.col("__n").alias(name))


def answer_stats(answers: DataFrame) -> DataFrame:
    """(rows, and for each variable its distinct values and the share of rows that bind it)."""
    cols = [x for c in answers.columns for x in (F.count_distinct(c).alias(f"{c}_distinct"), F.avg(F.col(c).isNotNull().cast("double")).alias(f"{c}_bound"))]
    return answers.agg(F.count("*").alias("rows"), *cols)
