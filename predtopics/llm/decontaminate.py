"""Benchmark decontamination: a prefix-filtered containment join, in DataFrame expressions only.

Every benchmark item gives windows of ``size`` consecutive words (one shorter window if the item has fewer). Words are
ordered by rarity, counted over all documents. A window is contained in a document only if all its
words are, so the necessary prefix of a window in that order is its rarest word: documents are joined on
that word alone. The place of the word in the window and in the document gives the only possible start (positional bound),
the window must fit between start and the document's end (length bound), and what is left is verified word by word.

Documents are read twice (counting, joining) and never shuffled as texts. The windows are broadcast if
they are at most ``most``; more of them are joined by shuffle, with the neighbourhood of each word, and the occurrences of words that are
frequent in the documents are dealt to several tasks. Windows with the same items share a number, and an occurrence carries only that;
the items come to the documents at the end.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, HOT_PART, checkpoint, join_unique, sized, table

SIZE = 10
#: What stands between words, once A-Z are lower-cased.
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words(text: Column) -> Column:
    """Words of a text; null has none. Only A-Z are lower-cased: ``lower`` serves plain ASCII, ``translate`` the rest."""
    text = F.coalesce(text.cast("string"), F.lit(""))
    low = F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))
    return F.array_remove(F.split(low, BETWEEN, -1), "")


def windows(items: DataFrame, size: int = SIZE, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """(win, len, items): distinct windows with the ids, as strings, of the items that have them."""
    held = items.select(F.col(id_col).cast("string").alias("item"), words(F.col(text_col)).alias("w")).where("item is not null and size(w) > 0")
    length = F.least(F.size("w"), F.lit(size))
    at = held.select("item", "w", length.alias("len"), F.explode(F.sequence(F.lit(1), F.size("w") - length + 1)).alias("s"))
    return at.select("item", F.slice("w", F.col("s"), F.col("len")).alias("win"), "len").groupBy("win", "len").agg(F.sort_array(F.collect_set("item")).alias("items"))


def anchors(wins: DataFrame, docs_words: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """(token, offset, len, win, set, salts): windows with their rarest word, its place, and to how many tasks its occurrences are dealt."""
    vocabulary = wins.select(F.explode("win").alias("token")).distinct()
    counts = checkpoint(docs_words.select(F.explode("w").alias("token")).join(sized(vocabulary, most), "token").groupBy("token").count())
    keyed = wins.select("win", "len", "set", F.monotonically_increasing_id().alias("key"))
    placed = checkpoint(keyed.select("*", F.posexplode("win").alias("offset", "token")))
    rarity = F.coalesce("count", F.lit(0))
    rare = F.min(F.struct(rarity.alias("count"), "token", "offset", "win", "len", "set")).alias("rare")
    found = join_unique(placed, counts, ["token"], "left", most).groupBy("key").agg(rare).select("rare.*")
    part = F.greatest(F.lit(1.0), counts.agg(F.sum("count")).first()[0] / F.lit(float(HOT_PART))) if counts.limit(1).count() else F.lit(1.0)
    return found.select("token", "offset", "len", "win", "set", F.greatest(F.lit(1), F.ceil(F.col("count") / part)).cast("int").alias("salts"))


#: Marks that documents leave where windows are joined by shuffle, so that no task gets those of all documents.
MARKS = 4096


def matches(docs: DataFrame, items: DataFrame, size: int = SIZE, id_col: str = "doc_id", text_col: str = "text", most: int = BROADCAST_ROWS, item_id: str = "item_id", item_text: str = "text") -> tuple[DataFrame, DataFrame]:
    """(row, doc_id, n_words, start, len, set): each occurrence of a window, and for each document one row with len 0; and (set, items).

    ``row`` tells repeated rows and ids apart. Both are in the shared folder, so they are made once.
    """
    split = docs.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).alias("doc_id"), words(F.col(text_col)).alias("w"))
    wins = checkpoint(windows(items, size, item_id, item_text))
    sets = checkpoint(wins.select("items").distinct().select(F.monotonically_increasing_id().alias("set"), "items"))
    marked = checkpoint(anchors(checkpoint(wins.join(sized(sets), "items").select("win", "len", "set")), split, most))
    few = marked.limit(most + 1).count() <= most
    # a document's mark is no word, as words hold no such character
    mark = F.concat(F.lit("\0"), F.pmod(F.col("row"), F.lit(1 if few else MARKS)).cast("string"))
    marks = docs.sparkSession.range(1 if few else MARKS).select(F.concat(F.lit("\0"), F.col("id").cast("string")).alias("token"), F.lit(0).alias("offset"), F.lit(0).alias("len"), F.array(F.lit("")).alias("win"), F.lit(-1).cast("long").alias("set"), F.lit(1).alias("salts"))
    known = marks.unionByName(marked)
    ended = split.select("row", "doc_id", F.size("w").alias("n_words"), "w", F.array_append("w", mark).alias("all"))
    at = ended.select("row", "doc_id", "n_words", "w", F.posexplode("all").alias("pos", "token"))
    start = F.col("pos") - F.col("offset")
    fits = (start >= 0) & (start + F.col("len") <= F.col("n_words"))
    if few:
        same = F.slice("w", start + 1, F.col("len")) == F.col("win")
        found = at.join(F.broadcast(known), "token")
    else:
        low = F.greatest(F.col("pos") - size + 1, F.lit(0))
        is_mark = F.col("pos") == F.col("n_words")
        near = at.select("row", F.when(is_mark, F.col("doc_id")).alias("doc_id"), "n_words", "pos", "token", low.alias("low"), F.when(~is_mark, F.slice("w", low + 1, F.lit(2 * size))).alias("near"))
        dealt = known.where("salts > 1").select("token", "salts").distinct()  # at most HOT_PART tokens
        near = near.join(F.broadcast(dealt), "token", "left").withColumn("salt", F.when(F.col("salts") > 1, F.pmod(F.xxhash64("row", "pos"), F.col("salts"))).otherwise(F.lit(0)).cast("int")).drop("salts")
        spread = known.select("*", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt")).drop("salts")
        same = F.slice("near", start - F.col("low") + 1, F.col("len")) == F.col("win")
        found = near.join(spread, ["token", "salt"])
    found = found.where((F.col("len") == 0) | (F.when(fits, same).otherwise(F.lit(False))))
    return checkpoint(found.select("row", F.when(F.col("len") == 0, F.col("doc_id")).alias("doc_id"), "n_words", start.alias("start"), "len", "set")), sets


def contaminated(docs: DataFrame, items: DataFrame, size: int = SIZE, id_col: str = "doc_id", text_col: str = "text", most: int = BROADCAST_ROWS, item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """(doc_id) of the document rows, told apart by their ids, that have any word of a window, each once. Edge cases as in ``decontaminate``."""
    found, _ = matches(docs, items, size, id_col, text_col, most, item_id, item_text)
    hit = found.groupBy("row").agg(F.max("len").alias("len"), F.first("doc_id", ignorenulls=True).alias("doc_id"))
    return hit.where("len > 0").select("doc_id").distinct()


def decontaminate(docs: DataFrame, items: DataFrame, size: int = SIZE, id_col: str = "doc_id", text_col: str = "text", most: int = BROADCAST_ROWS, item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row per document row: (row, doc_id, n_words, n_hit, n_items, item_ids).

    A word is hit if it lies in any occurrence of a window. item_ids are sorted strings. Null and empty texts have no
    words and no hits; items without id or words take no part; repeated document rows stay repeated; ids
    may be null; empty frames give empty results or no hits. Other columns are ignored.
    """
    found, sets = matches(docs, items, size, id_col, text_col, most, item_id, item_text)
    hits = found.where("len > 0")
    # words of a document that occurrences cover: each adds what reaches beyond those before it
    before = F.struct(F.lit(0).alias("end"), F.lit(0).alias("n"))
    reach = lambda acc, x: F.struct(F.greatest(acc["end"], x["start"] + x["len"]).alias("end"), (acc["n"] + F.greatest(F.lit(0), x["start"] + x["len"] - F.greatest(acc["end"], x["start"]))).alias("n"))
    places = F.sort_array(F.collect_set(F.struct("start", "len")))
    covered = hits.groupBy("row").agg(F.aggregate(places, before, reach, lambda acc: acc["n"]).alias("n_hit"))
    of_row = checkpoint(hits.select("row", "set").distinct())
    named = join_unique(of_row, sets, ["set"]).groupBy("row").agg(F.sort_array(F.array_distinct(F.flatten(F.collect_list("items")))).alias("item_ids"))
    base = found.where("len = 0").select("row", "doc_id", F.col("n_words").cast("long").alias("n_words"))
    out = base.join(covered, "row", "left").join(named, "row", "left")
    ids = F.coalesce("item_ids", F.array().cast("array<string>"))
    return out.select("row", "doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.size(ids).cast("long").alias("n_items"), ids.alias("item_ids"))


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))
    return found.select(
        "doc_id", "n_words", "n_hit", "n_items", F.sha2(F.concat_ws(",", "item_ids"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated")
    )


ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark WHERE item_id IS NOT NULL),
s AS (SELECT item_id, w, least(len(w), 10) AS l, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS a FROM b WHERE len(w) > 0),
g AS (SELECT DISTINCT item_id, l, array_to_string(w[a:a + l - 1], ' ') AS win FROM s),
ls AS (SELECT DISTINCT l FROM g),
p AS (SELECT r, l, w, unnest(range(1, len(w) - l + 2)) AS a FROM d, ls WHERE len(w) >= l),
q AS (SELECT r, l, a, array_to_string(w[a:a + l - 1], ' ') AS win FROM p),
m AS (SELECT q.r, q.l, q.a, g.item_id FROM q JOIN g ON q.win = g.win AND q.l = g.l),
h AS (SELECT r, count(DISTINCT x) AS n_hit FROM (SELECT r, unnest(range(a, a + l)) AS x FROM m) GROUP BY r),
i AS (SELECT r, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT r, CAST(item_id AS VARCHAR) AS item FROM m) GROUP BY r)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(h.n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(i.n_items, 0) AS BIGINT) AS n_items,
sha256(coalesce(i.items, '')) AS items_sha256, coalesce(h.n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (r) LEFT JOIN i USING (r)
"""
