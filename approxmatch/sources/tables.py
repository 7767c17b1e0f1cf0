"""The given tables, base relations made from them, and files in other formats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.index import relation
from ..operators.storage import spread

FORMATS = ("parquet", "csv", "json", "orc", "text")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_relation(spark: SparkSession, path: str, fmt: str = "parquet", id_col: str = "tid", str_col: str = "s") -> DataFrame:
    """A base relation from files, with an explicit schema. Text files number their lines by a hash-free running id."""
    if fmt not in FORMATS:
        raise ValueError(f"unknown format {fmt!r}; one of {', '.join(FORMATS)}")
    if fmt == "text":
        return spark.read.text(path).select(F.monotonically_increasing_id().alias("tid"), F.col("value").alias("s"))
    reader = spark.read.format(fmt)
    if fmt in ("csv", "json"):
        reader = reader.schema(T.StructType([T.StructField(id_col, T.LongType()), T.StructField(str_col, T.StringType())]))
    return relation(reader.option("header", "true").load(path) if fmt == "csv" else reader.load(path), id_col, str_col)


def write_relation(rel: DataFrame, path: str, fmt: str = "parquet") -> None:
    if fmt not in FORMATS:
        raise ValueError(f"unknown format {fmt!r}; one of {', '.join(FORMATS)}")
    out = rel.select("s") if fmt == "text" else rel
    writer = out.write.mode("overwrite").format(fmt)
    (writer.option("header", "true") if fmt == "csv" else writer).save(path)


def write_scores(scores: DataFrame, path: str, buckets: int = 16) -> None:
    """Scores as Parquet in folders by a hash bucket of the query, so that a query is found without a full scan."""
    scores.withColumn("qid_bucket", F.pmod(F.xxhash64("qid"), F.lit(buckets))).write.mode("overwrite").partitionBy("qid_bucket").parquet(path)


def part_desc(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = F.concat_ws(" ", "p_name", "p_type", F.expr("substr(p_brand, 7)"))
    return relation(load(spark, sf_dir, "part"), "p_partkey", s)


def part_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relation(load(spark, sf_dir, "part"), "p_partkey", F.concat_ws(" ", "p_name", "p_brand", "p_type"))


def names(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """supplier, customer, nation or region names."""
    key, name = {"supplier": ("s_suppkey", "s_name"), "customer": ("c_custkey", "c_name"), "nation": ("n_nationkey", "n_name"), "region": ("r_regionkey", "r_name")}[table]
    return relation(load(spark, sf_dir, table), key, name)


def doc_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relation(load(spark, sf_dir, "documents"), "doc_id", "text")


def passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "benchmark").select(F.col("item_id").cast("long").alias("qid"), F.col("text").alias("s"))


def page_title(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relation(load(spark, sf_dir, "pages"), "page_id", F.regexp_extract("html", r"<title>([^<]*)</title>", 1))


def _draw(key: str) -> Column:
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{key}|"), F.col("doc_id").cast("string")).cast("binary")), 1, 8), 16, 10).cast("long")


def _clean_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    lowered = F.trim(F.regexp_replace(F.regexp_replace(F.lower("text"), r"[^\p{L}\p{N}_ ]", " "), r"\s+", " "))
    rows = spread(load(spark, sf_dir, "documents").where("text is not null").select("doc_id", "text")).select("doc_id", F.split(lowered, " ").alias("w"))
    return rows.where(F.size("w") >= 12)


def short_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stand-in for a list of company names: one or two invented words and a legal form, stems distinct."""
    from ..operators.datagen import FORMS

    rows = _clean_words(spark, sf_dir)
    n = F.when(F.col("doc_id") % 12 == 0, 1).otherwise(2)
    start = _draw("name") % (F.size("w") - 2) + 1
    stem = F.array_join(F.slice("w", start.cast("int"), n), " ")
    forms = F.array(*(F.lit(x) for pair in FORMS for x in pair))
    # unevenly likely: 3 : 2 : 2 : 1, short and long form alike
    which = F.element_at(F.array(*(F.lit(i) for i in (0, 0, 0, 1, 1, 2, 2, 3))), (_draw("form") % 8 + 1).cast("int"))
    form = F.element_at(forms, (which * 2 + _draw("length") % 2 + 1).cast("int"))
    rows = rows.select(F.col("doc_id").alias("tid"), stem.alias("stem"), form.alias("form"))
    first = rows.groupBy("stem").agg(F.min(F.struct("tid", "form")).alias("x"))
    return first.select(F.col("x.tid").alias("tid"), F.concat_ws(" ", "stem", "x.form").alias("s"))


def long_titles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stand-in for a list of titles: windows of five to seven words."""
    rows = _clean_words(spark, sf_dir)
    n = (_draw("count") % 3 + 5).cast("int")
    start = (_draw("title") % (F.size("w") - 7) + 1).cast("int")
    return rows.select(F.col("doc_id").alias("tid"), F.array_join(F.slice("w", start, n), " ").alias("s"))


__all__ = ["Window", "doc_text", "load", "long_titles", "names", "page_title", "part_desc", "part_full", "passages", "read_relation", "short_names", "write_relation", "write_scores"]
