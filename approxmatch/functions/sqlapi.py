"""SQL surface: views over an index, and functions for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, Row

from .strsim import jaro_of, jaro_winkler_of


def register_views(index, prefix: str) -> None:
    """<prefix>_rows, <prefix>_postings, <prefix>_stats, <prefix>_meta."""
    spark = index.rows.sparkSession
    index.rows.createOrReplaceTempView(f"{prefix}_rows")
    index.postings.createOrReplaceTempView(f"{prefix}_postings")
    index.stats.createOrReplaceTempView(f"{prefix}_stats")
    m = index.meta
    spark.createDataFrame([(m.n, m.cs, m.avgdl, m.mean_idf)], "n long, cs long, avgdl double, mean_idf double").createOrReplaceTempView(f"{prefix}_meta")


def sql_select(spark: SparkSession, statement: str, **args) -> DataFrame:
    """A statement over registered views, with named parameters."""
    return spark.sql(statement, args=args or None)


def register_functions(spark: SparkSession) -> None:
    """edit_similarity and qgram_list as SQL expressions; jaro, jaro_winkler as vectorised UDFs; tokens as a UDTF."""
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION edit_similarity(a STRING, b STRING) RETURNS DOUBLE
        RETURN CASE WHEN greatest(length(a), length(b)) = 0 THEN 1D ELSE 1D - CAST(levenshtein(a, b) AS DOUBLE) / greatest(length(a), length(b), 1) END""")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION qgram_list(s STRING, q INT) RETURNS ARRAY<STRING>
        RETURN CASE WHEN length(trim(s)) > 0 THEN transform(sequence(1, length(repeat('$', q - 1) || replace(trim(s), ' ', repeat('$', q - 1)) || repeat('$', q - 1)) - q + 1),
          i -> substring(repeat('$', q - 1) || replace(trim(s), ' ', repeat('$', q - 1)) || repeat('$', q - 1), i, q)) ELSE array() END""")

    @F.pandas_udf(DoubleType())
    def jw(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else jaro_winkler_of(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")

    @F.pandas_udf(DoubleType())
    def ja(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else jaro_of(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")

    @F.udtf(returnType="pos int, token string")
    class Tokens:
        def eval(self, s: str, q: int) -> Iterator[Row]:
            pads = "$" * (q - 1)
            if s and s.strip():
                p = pads + " ".join(s.split()).replace(" ", pads) + pads
                yield from ((i, p[i : i + q]) for i in range(len(p) - q + 1))

    spark.udf.register("jaro_winkler", jw)
    spark.udf.register("jaro", ja)
    spark.udtf.register("tokens", Tokens)
