"""Secret scans in DataFrame expressions only: known patterns, and high-entropy strings by a sliding window.

Places of matches come from what lies between them: ``split`` gives the gaps and ``regexp_extract_all`` the matches of one
pattern, and running sums of their lengths give starts and ends in code points. Every text is scanned in its own row;
nothing is shuffled.

Candidate strings for entropy are runs of key characters with a digit and a letter. Each belongs to one
class (hex, upper, mixed), and a window of ``WINDOW`` characters slides over it: the counts of the window's characters are kept
in an array, a step adds the character that enters and takes off the one that leaves, and the sum of c*log2(c) follows these
two counts. The highest entropy of a window is held against the class's threshold. Strings of the allow-list
are left out, and so are those inside a base span.

Time grows with the length of a text and with its matches, not with their squares: running sums and maxima are taken in runs of
``RUN`` values, as what an aggregation holds is copied at each step.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: The base patterns with the group whose length counts, and that length.
BASE = {
    "assign": (r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    "access": (r"AKIA[A-Z0-9]+", 0, 16),
    "hex": (r"[0-9a-f]{32,}", 0, 32),  # runs are whole, so this finds those of [0-9a-f]+ with 32 or more
}
CANDIDATE = r"[A-Za-z0-9+/_-]{20,}={0,2}"
WINDOW = 20
#: Character classes in the order they are tried, with bits of entropy that a window must reach.
CLASSES = (("hex", r"^(?:[0-9a-f]+|[0-9A-F]+)$", "0123456789abcdefABCDEF", 2.8), ("upper", r"^[A-Z0-9]+$", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ", 3.4), ("mixed", r"", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz+/_-=", 3.75))
#: Values of a running sum that are taken at once.
RUN = 256
#: Strings that look random or keyed but are public by nature: identifiers in the standard 8-4-4-4-12 form, samples, alphabets, dates, paths and slugs of words.
ALLOW = (
    r"^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    r"(?i)example|sample|placeholder|changeme|dummy|xxxx|your[_-]",
    r"(?i)0123456789|abcdefghij|qwertyuiop",
    r"^\d{4}-\d\d-\d\d",
    r"^/?(?:v[0-9]++|[a-z]++|[0-9]{1,4}+)(?:[/_-](?:v[0-9]++|[a-z]++|[0-9]{1,4}+))++/?$",  # possessive, so that long strings take no stack
)
SPAN = "array<struct<start:int,rank:int,end:int,kind:string>>"


def _bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is worked out once."""
    return F.get(F.transform(F.array(value), body), 0)


def _runs(values: Column) -> Column:
    """An array in runs of RUN values."""
    starts = F.sequence(F.lit(0), F.greatest(F.ceil(F.size(values) / RUN).cast("int") - 1, F.lit(0)))
    return F.transform(starts, lambda j: F.slice(values, j * RUN + 1, F.lit(RUN)))


def ahead(values: Column, joined: Callable[[Column, Column], Column]) -> Column:
    """For each of some whole numbers what those ahead of it join to; 0 for the first."""
    zero, none = F.lit(0), F.array().cast("array<int>")

    def within(run: Column, first: Column) -> Column:
        step = lambda acc, v: F.struct(joined(acc["at"], v).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out"))
        return F.aggregate(run, F.struct(first.alias("at"), none.alias("out")), step, lambda acc: acc["out"])

    def of_runs(runs: Column) -> Column:
        wholes = F.transform(runs, lambda run: F.aggregate(run, zero, joined))
        return _bound(within(wholes, zero), lambda heads: F.flatten(F.transform(runs, lambda run, j: within(run, F.get(heads, j)))))

    return _bound(_runs(values), of_runs)


def _located(matches: Column, gaps: Column, keep: Column, kind: str, rank: int) -> Column:
    """Spans of matches, given the gaps before them and which of them to keep."""

    def placed(x: Column) -> Column:  # bound, as an expression within a lambda would be worked out for each match
        def span(hit: Column, i: Column) -> Column:
            start = F.get(x["before"], i) + F.length(F.get(x["gaps"], i))
            return F.when(F.get(x["keep"], i), F.struct(start.alias("start"), F.lit(rank).alias("rank"), (start + F.length(hit)).alias("end"), F.lit(kind).alias("kind")))

        return F.filter(F.transform(x["matches"], span), lambda y: y.isNotNull())

    def sized(x: Column) -> Column:
        size = F.transform(x["matches"], lambda hit, i: F.length(F.get(x["gaps"], i)) + F.length(hit))
        return _bound(F.struct(x["matches"].alias("matches"), x["gaps"].alias("gaps"), x["keep"].alias("keep"), ahead(size, lambda a, b: a + b).alias("before")), placed)

    return _bound(F.struct(matches.alias("matches"), gaps.alias("gaps"), keep.alias("keep")), sized).cast(SPAN)


def _long_enough(values: Column, least: int) -> Column:
    return F.transform(values, lambda v: F.length(v) >= least)


def best_entropy(text: Column, window: int = WINDOW) -> Column:
    """Highest Shannon entropy, in bits, of the windows of ``text`` (of all of it, if shorter)."""
    part = lambda c: F.when(c > 0, c * F.log2(c.cast("double"))).otherwise(F.lit(0.0))

    def over(x: Column) -> Column:
        places, width = x["places"], x["width"]

        def step(acc: Column, i: Column) -> Column:
            enters = F.get(places, i - 1)
            leaves = F.when(i > width, F.get(places, i - width - 1)).otherwise(F.lit(0))
            same = enters == leaves
            up = F.coalesce(F.get(acc["counts"], enters - 1), F.lit(0))
            down = F.coalesce(F.get(acc["counts"], leaves - 1), F.lit(0))
            grown = acc["sum"] + F.when(same, F.lit(0.0)).otherwise(part(up + 1) - part(up) + F.when(leaves > 0, part(down - 1) - part(down)).otherwise(F.lit(0.0)))
            counts = F.when(same, acc["counts"]).otherwise(F.transform(acc["counts"], lambda c, j: c + F.when(j == enters - 1, 1).when(j == leaves - 1, -1).otherwise(0)))
            now = F.log2(width.cast("double")) - grown / width
            return F.struct(counts.alias("counts"), grown.alias("sum"), F.when(i >= width, F.greatest(acc["best"], now)).otherwise(acc["best"]).alias("best"))

        zero = F.struct(F.array_repeat(F.lit(0), x["letters"]).alias("counts"), F.lit(0.0).alias("sum"), F.lit(0.0).alias("best"))
        return F.aggregate(F.sequence(F.lit(1), F.size(places)), zero, step, lambda acc: acc["best"])

    def numbered(x: Column) -> Column:  # each character as its place among those of the text
        places = F.transform(x["chars"], lambda c: F.array_position(x["letters"], c).cast("int"))
        return F.struct(places.alias("places"), F.size(x["letters"]).alias("letters"), F.least(F.size(x["chars"]), F.lit(window)).alias("width"))

    def lettered(chars: Column) -> Column:
        return F.struct(chars.alias("chars"), F.array_distinct(chars).alias("letters"))

    chars = F.filter(F.split(text, ""), lambda c: c != "")
    return _bound(_bound(_bound(chars, lettered), numbered), over)


def _random_looking(text: Column, allow: tuple[str, ...]) -> Column:
    """Whether a candidate reaches its class's threshold and no pattern of the allow-list has it."""
    least, known = F.lit(0.0), F.lit(False)
    for _, pattern, _, bits in reversed(CLASSES):
        least = F.when(text.rlike(pattern), bits).otherwise(least) if pattern else F.lit(bits)
    for pattern in allow:
        known = known | text.rlike(pattern)
    keyed = text.rlike("[0-9]") & text.rlike("[A-Za-z]")
    return F.when(keyed & ~known, best_entropy(text) >= least).otherwise(F.lit(False))


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", allow: tuple[str, ...] = ALLOW) -> DataFrame:
    """(doc_id, text, base, extra, spans) of every row; spans are structs (start, rank, end, kind) sorted by start, then kind as listed.

    base holds the pattern spans, extra those of the entropy method, spans both. Offsets count code points. Null text is an
    empty one, without spans; repeated rows and null ids stay; an empty frame gives an empty one. Other columns are ignored.
    """
    cur = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    none, patterns = F.array().cast("array<string>"), {k: v[0] for k, v in BASE.items()} | {"entropy": CANDIDATE}
    quick = {"access": F.col("text").contains("AKIA")}
    cur = cur.select("*", *[quick.get(k, F.col("text").rlike(p)).alias(f"has_{k}") for k, p in patterns.items()])
    columns = []
    for k, p in patterns.items():
        has = F.col(f"has_{k}")
        group = BASE[k][1] if k in BASE else 0
        columns += [F.when(has, F.regexp_extract_all("text", F.lit(p), F.lit(0))).otherwise(none).alias(f"hit_{k}"), F.when(has, F.split("text", p, -1)).otherwise(none).alias(f"gap_{k}")]
        columns += [F.when(has, F.regexp_extract_all("text", F.lit(p), F.lit(group))).otherwise(none).alias(f"val_{k}")] if group else []
    cur = cur.select("doc_id", "text", *columns)
    spans = []
    for rank, k in enumerate(patterns):
        hit = F.col(f"hit_{k}")
        if k in BASE:
            value = F.col(f"val_{k}") if BASE[k][1] else hit
            keep = _long_enough(value, BASE[k][2])
        else:
            keep = F.transform(hit, lambda v: _random_looking(v, allow))
        spans.append(_located(hit, F.col(f"gap_{k}"), keep, k, rank).alias(f"at_{k}"))
    cur = cur.select("doc_id", "text", *spans)
    cur = cur.select("doc_id", "text", F.array_sort(F.concat(*[f"at_{k}" for k in BASE])).alias("base"), "at_entropy")
    cur = cur.select("doc_id", "text", "base", F.array_sort(F.concat("base", "at_entropy")).alias("all"))
    # of spans by start the base ones come first, so a span lies in a base one if any ahead of it ends as late
    reach = ahead(F.transform("all", lambda x: F.when(x["rank"] < len(BASE), x["end"]).otherwise(0)), lambda a, b: F.greatest(a, b))
    spans = _bound(reach, lambda reach: F.filter("all", lambda x, i: (x["rank"] < len(BASE)) | (F.get(reach, i) < x["end"])))
    cur = cur.select("doc_id", "text", "base", spans.alias("spans"))
    return cur.select("doc_id", "text", "base", F.filter("spans", lambda x: x["rank"] == len(BASE)).alias("extra"), "spans")


def listed(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))))


def redacted(text: Column, spans: Column, mark: str = "[SECRET]") -> Column:
    """Text with every sorted span, and overlapping ones as one, put as ``mark``."""
    told = F.transform(spans, lambda x: x["end"])

    def cut(before: Column) -> Column:
        known = F.transform(spans, lambda x, i: F.struct(x["start"].alias("start"), x["end"].alias("end"), F.get(before, i).alias("done")))

        def of_run(run: Column) -> Column:  # with its own part of the text, so that the whole one is not walked for each span
            first, last = F.get(run, 0)["done"], F.array_max(F.transform(run, lambda x: F.greatest(x["end"], x["done"])))
            pieces = lambda part: F.transform(run, lambda x: F.concat(F.substring(part, x["done"] - first + 1, F.greatest(x["start"] - x["done"], F.lit(0))), F.when(x["start"] >= x["done"], F.lit(mark)).otherwise(F.lit(""))))
            return F.array_join(_bound(F.substring(text, first + 1, last - first), pieces), "")

        tail = F.greatest(F.array_max(told), F.lit(0))
        return F.concat(F.array_join(_bound(_runs(known), lambda runs: F.transform(runs, of_run)), ""), F.substring(text, tail + 1, F.length(text)))

    return F.when(F.size(spans) == 0, text).otherwise(_bound(ahead(told, lambda a, b: F.greatest(a, b)), cut))


def op6_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_secrets(table(spark, sf_dir, "documents", "doc_id", "text"))
    count = lambda k: F.size(F.filter("base", lambda x: x["kind"] == k)).cast("long").alias(f"n_{k}")
    return found.select("doc_id", *[count(k) for k in BASE], F.sha2(listed(F.col("base")), 256).alias("base_sha256"), listed(F.col("spans")).alias("spans"))


def _oracle() -> str:
    """The same spans in SQL: entropy is worked out for each window anew, and possessive repeats, which its patterns lack, are plain ones."""
    patterns = {k: v[0] for k, v in BASE.items()} | {"entropy": CANDIDATE}
    literal = lambda x: "'" + x.replace("'", "''") + "'"
    found = " UNION ALL ".join(f"SELECT r, {n} AS rank, {literal(k)} AS kind, t, regexp_extract_all(t, {literal(p)}) AS hits, regexp_split_to_array(t, {literal(p)}) AS gaps FROM d" for n, (k, p) in enumerate(patterns.items()))
    value = f"CASE WHEN rank = 0 THEN regexp_extract(hit, {literal(BASE['assign'][0])}, {BASE['assign'][1]}) ELSE hit END"
    least = " ".join(f"WHEN rank = {n} THEN {v[2]}" for n, v in enumerate(BASE.values()))
    bits = "CASE " + " ".join(f"WHEN regexp_matches(hit, {literal(p)}) THEN {b}" for _, p, _, b in CLASSES if p) + f" ELSE {CLASSES[-1][3]} END"
    known = " OR ".join(f"regexp_matches(hit, {literal(p.replace('++', '+').replace('}+', '}'))})" for p in ALLOW)
    return f"""
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
f AS (SELECT r, rank, kind, hits, gaps FROM ({found}) WHERE len(hits) > 0),
e AS (SELECT r, rank, kind, unnest(generate_series(1, len(hits))) AS j, unnest(hits) AS hit, unnest(gaps[1:len(hits)]) AS gap FROM f),
p AS MATERIALIZED (SELECT r, rank, kind, hit, sum(length(gap) + length(hit)) OVER (PARTITION BY r, rank ORDER BY j) AS e FROM e),
b AS MATERIALIZED (SELECT r, rank, kind, e - length(hit) AS s, e FROM p WHERE rank < {len(BASE)} AND length({value}) >= CASE {least} END),
c AS MATERIALIZED (SELECT DISTINCT hit, {bits} AS bits FROM p WHERE rank = {len(BASE)} AND regexp_matches(hit, '[0-9]') AND regexp_matches(hit, '[A-Za-z]') AND NOT ({known})),
w AS (SELECT hit, bits, first, substr(hit, first, {WINDOW}) AS part FROM (SELECT hit, bits, unnest(generate_series(1, length(hit) - {WINDOW} + 1)) AS first FROM c)),
l AS (SELECT hit, bits, first, letter, count(*) / {float(WINDOW)} AS share FROM (SELECT hit, bits, first, unnest(string_split(part, '')) AS letter FROM w) GROUP BY ALL),
h AS MATERIALIZED (SELECT hit FROM (SELECT hit, bits, first, -sum(share * log2(share)) AS entropy FROM l GROUP BY ALL) GROUP BY hit HAVING max(entropy) >= any_value(bits)),
x AS (SELECT p.r, p.rank, p.kind, p.e - length(p.hit) AS s, p.e FROM p JOIN h ON h.hit = p.hit WHERE p.rank = {len(BASE)} AND NOT EXISTS (SELECT 1 FROM b WHERE b.r = p.r AND b.s <= p.e - length(p.hit) AND b.e >= p.e)),
o AS (SELECT r, {", ".join(f"count(*) FILTER (kind = {literal(k)}) AS n_{k}" for k in BASE)}, string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, rank) FILTER (rank < {len(BASE)}) AS base, string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, rank) AS spans FROM (SELECT * FROM b UNION ALL SELECT * FROM x) GROUP BY r)
SELECT d.doc_id, {", ".join(f"CAST(coalesce(o.n_{k}, 0) AS BIGINT) AS n_{k}" for k in BASE)}, sha256(coalesce(o.base, '')) AS base_sha256, coalesce(o.spans, '') AS spans FROM d LEFT JOIN o ON o.r = d.r
"""


ORACLE = _oracle()
