"""Readers and writers: the given tables, fact text, and round trips through formats."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..settle import shared_dir

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def stamp(spark: SparkSession, sf_dir: str) -> int:
    """A number that changes when a table of the folder is written anew: from names, lengths and times of what lies in it."""
    at = spark._jvm.org.apache.hadoop.fs.Path(sf_dir)
    found = at.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(at)
    return hash(tuple(sorted((f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in found)))


def register(spark: SparkSession, sf_dir: str, prefix: str = "") -> None:
    """All tables as temporary views."""
    for name in NAMES:
        load_table(spark, sf_dir, name).createOrReplaceTempView(prefix + name)


def counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(name, n): rows per table, from the files' footers where the reader can."""
    out = None
    for name in NAMES:
        one = load_table(spark, sf_dir, name).agg(F.count("*").alias("n")).select(F.lit(name).alias("name"), "n")
        out = one if out is None else out.unionAll(one)
    return out


def scratch(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def write_facts_text(facts: DataFrame, path: str) -> str:
    """One fact a line: <s> <p> "o" . with backslash, quote and line ends escaped."""
    safe = F.regexp_replace(F.regexp_replace(F.regexp_replace("o", r"\\", r"\\\\"), '"', r'\\"'), "\n", r"\\n")
    facts.select(F.concat(F.lit("<"), "s", F.lit("> <"), "p", F.lit('> "'), safe, F.lit('" .')).alias("value")).write.mode("overwrite").text(path)
    return path


def read_facts_text(spark: SparkSession, path: str) -> DataFrame:
    """(s, p, o) of fact lines; lines of another form are left out."""
    line = r'^<([^>]*)> <([^>]*)> "(.*)" \.$'
    rows = spark.read.text(path).where(F.col("value").rlike(line))
    raw = F.regexp_extract("value", line, 3)
    plain = F.regexp_replace(F.regexp_replace(F.regexp_replace(raw, r"(?<!\\)((?:\\\\)*)\\n", "$1\n"), r'\\"', '"'), r"\\\\", r"\\")
    return rows.select(F.regexp_extract("value", line, 1).alias("s"), F.regexp_extract("value", line, 2).alias("p"), plain.alias("o"))


def roundtrip(df: DataFrame, fmt: str) -> DataFrame:
    """Write and read back with the schema given, so nothing is inferred."""
    path = scratch(df.sparkSession, fmt)
    options = {"header": "true"} if fmt == "csv" else {}
    df.write.format(fmt).options(**options).mode("overwrite").save(path)
    return df.sparkSession.read.format(fmt).options(**options).schema(df.schema).load(path)


def write_facts(facts: DataFrame, path: str, partition: str = "p") -> str:
    """Facts by predicate, so that a pattern of one predicate reads one folder."""
    facts.repartition(partition).write.mode("overwrite").partitionBy(partition).parquet(path)
    return path
