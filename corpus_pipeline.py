"""A cleaning pipeline over ``documents``: language, near-duplicates, contamination, secrets, token ids.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and reread as the next stage's docs. All but the
last return the columns of ``documents``; a stage's decisions take effect on what it returns.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predtopics.llm import bpe, decontaminate, language, secrets, simhash
from predtopics.llm.common import checkpoint, discard, shared_dir, sized, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Folders of rows with keys that stages have written and whose readers are not done.
_WRITTEN: list[str] = []


def _documents(df: DataFrame) -> DataFrame:
    return df.select(*COLUMNS)


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text has a language; texts without a letter, and null ones, go. ``lang`` stays as given, and null ones are filled in."""
    net = language.train(docs)
    found = language.identify(docs, net, COLUMNS[:1] + COLUMNS[2:] + ("text",))
    return _documents(found.where("lang_pred <> 'und'").withColumn("lang", F.coalesce("lang", "lang_pred")))


def _keyed(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The documents with a key of their own for each row, written once so that it stays the same."""
    at = f"{shared_dir(spark)}/keyed-rows-{uuid.uuid4().hex}"
    _WRITTEN.append(at)
    docs.select(F.monotonically_increasing_id().alias("row"), *COLUMNS).write.parquet(at)
    return spark.read.parquet(at)


def _without(rows: DataFrame, gone: DataFrame) -> DataFrame:
    """Rows whose key is not in ``gone`` (row); texts are shuffled only if more keys go than may be broadcast."""
    return _documents(rows.join(sized(checkpoint(gone)), "row", "left_anti"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each SimHash class: that of the smallest doc_id, rows without id last; of repeated ids the one with the least text.

    Rows are told apart by a key of their own, so that each of repeated or missing ids is classed by its own text.
    """
    rows = _keyed(spark, docs)
    ident = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")
    found = checkpoint(simhash.near_duplicates(rows.select(ident.alias("id"), "text"), "id").select(F.col("doc_id.row").alias("row"), F.col("doc_id.doc_id").alias("own"), F.col("component_id.doc_id").alias("least"), F.col("component_id.row").alias("class")))
    later = found.where(~F.col("own").eqNullSafe(F.col("least"))).select("row")
    first = found.where(F.col("own").eqNullSafe(F.col("least"))).select("class", "row")
    several = first.groupBy("class").count().where("count > 1").select("class")
    tied = checkpoint(first.join(several, "class"))
    told = tied.join(rows, "row").select("class", F.struct("text", "lang", "source", "n_chars", "row").alias("r"))
    least = told.groupBy("class").agg(F.min("r").alias("r")).select(F.col("r.row").alias("row"))
    return _without(rows, later.unionByName(tied.select("row").join(least, "row", "left_anti")))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows without any word of a benchmark window."""
    rows = _keyed(spark, docs)
    hit = decontaminate.contaminated(rows.select("row", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"), id_col="row")
    return _without(rows, hit.withColumnRenamed("doc_id", "row"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, with secrets put as a mark and ``n_chars`` counted anew where there were any. Null texts stay null."""
    found = secrets.find_secrets(docs.select(F.struct(*COLUMNS).alias("doc"), "text"), id_col="doc")
    clean = found.select("doc_id.*", secrets.redacted(F.col("text"), F.col("spans")).alias("clean"), F.size("spans").alias("n"))
    text = F.when(F.col("n") > 0, F.col("clean")).otherwise(F.col("text"))
    chars = F.when(F.col("n") > 0, F.length("clean").cast("long")).otherwise(F.col("n_chars"))
    return clean.select("doc_id", text.alias("text"), "lang", "source", chars.alias("n_chars"))


def encode_and_decode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text (little-endian 32-bit), their number, and whether decoding gives the text back."""
    text = F.coalesce("text", F.lit(""))
    told = docs.select(F.struct("doc_id", F.xxhash64(text).alias("h"), F.length(text).alias("n")).alias("doc"), "text")
    coded = bpe.encode(told, id_col="doc", back=True)
    same = (F.col("doc_id.h") == F.xxhash64("text")) & (F.col("doc_id.n") == F.length("text"))
    return coded.select("doc_id.doc_id", "ids", F.size("ids").cast("long").alias("n_tokens"), same.alias("round_trip"))


STAGES = [
    ("language_id", identify_language),
    ("simhash_near_dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("secret_scans", redact_secrets),
    ("bpe", encode_and_decode),
]

#: SQL cannot express the network, the fingerprints or the tokenizer; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage. What stages have written between them goes as soon as the next stage's output stands."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    at = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for n, (name, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.mode("overwrite").parquet(f"{at}/{n}-{name}")
        docs = spark.read.parquet(f"{at}/{n}-{name}")
        for done in [*_WRITTEN, *([f"{at}/{n - 1}-{STAGES[n - 1][0]}"] if n else [])]:
            discard(spark, done)
        _WRITTEN.clear()
    return docs
