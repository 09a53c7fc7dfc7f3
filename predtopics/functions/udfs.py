"""Arrow and SQL user functions, for comparison with the built-in forms."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, IntegerType, StringType, StructField, StructType


@pandas_udf(DoubleType())
def share_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    """Share score of two arrays of distinct concepts."""
    return pd.Series([len(set(x) & set(y)) ** 2 / (len(x) * len(y)) for x, y in zip(a, b)])


@pandas_udf(DoubleType())
def mean_udaf(v: pd.Series) -> float:
    return float(v.mean())


@udtf(returnType=StructType([StructField("step", IntegerType()), StructField("p", StringType())]))
class WalkSteps:
    """Steps of a walk written as p1>p2>p3."""

    def eval(self, path: str):  # noqa: A003, ANN201
        for n, p in enumerate(path.split(">")):
            yield n + 1, p


def register(spark: SparkSession) -> None:
    """share_of(n12, n1, n2) in SQL, and the table function walk_steps."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION share_of(n12 BIGINT, n1 BIGINT, n2 BIGINT) RETURNS DOUBLE RETURN CAST(n12 * n12 AS DOUBLE) / (n1 * n2)")
    spark.udtf.register("walk_steps", WalkSteps)


def row_norms(df: DataFrame) -> DataFrame:
    """(p1, norm) by mapInPandas over (p1, values) rows."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"p1": b["p1"], "norm": [float((v * v).sum()) for v in b["values"]]})

    return df.mapInPandas(run, "p1 string, norm double")


def centred(df: DataFrame) -> DataFrame:
    """(p1, p2, centred): similarities less their row's mean, by applyInPandas."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pdf.assign(centred=pdf["sm"] - pdf["sm"].mean())[["p1", "p2", "centred"]]

    return df.groupBy("p1").applyInPandas(run, "p1 string, p2 string, centred double")


def matched(left: DataFrame, right: DataFrame) -> DataFrame:
    """(p1, rows, best): rows of a predicate on the left and its best similarity on the right, by a cogrouped map."""

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        key = a["p1"].iloc[0] if len(a) else b["p1"].iloc[0]
        return pd.DataFrame([{"p1": key, "rows": len(a), "best": float(b["sm"].max()) if len(b) else None}])

    return left.groupBy("p1").cogroup(right.groupBy("p1")).applyInPandas(run, "p1 string, rows long, best double")


def arrays(nbr: DataFrame) -> DataFrame:
    """(p, cs): neighbourhoods as sorted arrays."""
    return nbr.groupBy("p").agg(F.array_sort(F.collect_set("concept")).alias("cs"))
