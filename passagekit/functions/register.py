"""The engine's functions under names that SQL can call."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


@F.pandas_udf("double")
def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two vectors; null where one is null, zero or of another length."""

    def one(x, y):
        if x is None or y is None or len(x) != len(y):
            return None
        n = np.linalg.norm(x) * np.linalg.norm(y)
        return float(np.dot(x, y) / n) if n else None

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype="Float64")


@F.pandas_udf("double")
def crest(x: pd.Series) -> pd.Series:
    """Peak over root mean square of an array; null where there is none."""
    return pd.Series([None if v is None or not len(v) or not np.any(v) else float(np.max(np.abs(v)) / np.sqrt(np.mean(np.square(v)))) for v in x], dtype="Float64")


@F.pandas_udf("double")
def median_rank(rank: pd.Series) -> float:
    """An aggregate: the median of ranks."""
    return float(np.median(rank.dropna())) if rank.notna().any() else float("nan")


@F.udtf(returnType="start long, is_tail boolean")
class Windows:
    """A table function: windows of a recording, the last one ending at its end when the tail is long enough."""

    def eval(self, n_samples: int, width: int, least: int):
        if n_samples is None or n_samples < width:
            return
        for start in range(0, n_samples - width + 1, width):
            yield start, False
        if n_samples % width >= least and n_samples % width:
            yield n_samples - width, True


def top_hits(df, k: int = 1):
    """A grouped map: each query's k best rows in Arrow batches (query_id, gallery_id, sim)."""

    def run(parts: pd.DataFrame) -> pd.DataFrame:
        return parts.sort_values(["sim", "gallery_id"], ascending=[False, True]).head(k)

    return df.select("query_id", "gallery_id", "sim").groupBy("query_id").applyInPandas(run, "query_id long, gallery_id long, sim double")


def register(spark: SparkSession) -> None:
    """vec_dot, vec_cosine, crest, median_rank and windows for this session's SQL."""
    spark.sql("create or replace temporary function vec_dot(a array<double>, b array<double>) returns double return aggregate(zip_with(a, b, (x, y) -> x * y), 0d, (s, x) -> s + x)")
    spark.udf.register("vec_cosine", cosine)
    spark.udf.register("crest", crest)
    spark.udf.register("median_rank", median_rank)
    spark.udtf.register("windows", Windows)

