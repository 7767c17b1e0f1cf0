"""Accuracy and cost measures over rankings.

`ranked` has qid, tid, rank (O2). `truth` has qid, tid of the relevant tuples. `queries` has qid; queries without any
relevant result count as 0. `truth` may also be Classes, which never list the pairs.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from ..functions import weights
from .index import TokenIndex
from .storage import stored

#: Relevant tuples of a query up to which every returned tuple is compared with each of them.
FEW_RELEVANT = 64


@dataclass(frozen=True)
class Classes:
    """Truth by equality: relevant are the tuples (tid, class) of the query's class (qid, class), one class a row."""

    queries: DataFrame
    tuples: DataFrame


def relevant(truth: DataFrame | Classes) -> DataFrame:
    """qid, relevant: the number of relevant tuples, where there are any."""
    if isinstance(truth, Classes):
        sizes = truth.tuples.groupBy("class").agg(F.count(F.lit(1)).alias("relevant"))
        return truth.queries.join(sizes, "class").select("qid", "relevant")
    return truth.select("qid", "tid").distinct().groupBy("qid").agg(F.count(F.lit(1)).alias("relevant"))


def judged(ranked: DataFrame, truth: DataFrame | Classes) -> DataFrame:
    """ranked with rel (0 or 1)."""
    if isinstance(truth, Classes):
        out = ranked.join(truth.queries.select("qid", F.col("class").alias("asked")), "qid", "left").join(truth.tuples.select("tid", "class"), "tid", "left")
        return out.select("qid", "tid", *(c for c in ranked.columns if c not in ("qid", "tid")), F.when(F.col("asked") == F.col("class"), 1).otherwise(0).alias("rel"))
    marks = truth.select("qid", "tid", F.lit(1).alias("rel")).distinct()
    return ranked.join(marks, ["qid", "tid"], "left").withColumn("rel", F.coalesce("rel", F.lit(0)))


def pr_curve(ranked: DataFrame, truth: DataFrame | Classes) -> DataFrame:
    """qid, rank, rel, precision, recall at every rank; recall is over all relevant tuples, returned or not."""
    total = relevant(truth)
    running = Window.partitionBy("qid").orderBy("rank").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    hits = F.sum("rel").over(running).cast("double")
    return judged(ranked, truth).withColumn("hits", hits).join(total, "qid").select("qid", "tid", "rank", "rel", (F.col("hits") / F.col("rank")).alias("precision"), (F.col("hits") / F.col("relevant")).alias("recall"), "relevant")


def average_precision(ranked: DataFrame, truth: DataFrame | Classes, queries: DataFrame | None = None) -> DataFrame:
    """qid, ap: precision at each relevant rank, over the number of relevant tuples."""
    ap = pr_curve(ranked, truth).groupBy("qid").agg((F.sum(F.col("precision") * F.col("rel")) / F.max("relevant")).alias("ap"))
    if queries is None:
        return ap
    return queries.select("qid").distinct().join(ap, "qid", "left").select("qid", F.coalesce("ap", F.lit(0.0)).alias("ap"))


def _mean(values: DataFrame, name: str, copies: DataFrame | None) -> DataFrame:
    """The mean of a value of each query; with copies (qid, copies) each counts as often as it is asked."""
    if copies is None:
        return values.agg(F.avg(name).alias("mean"))
    return values.join(copies, "qid").agg((F.sum(F.col(name) * F.col("copies")) / F.sum("copies")).alias("mean"))


def mean_average_precision(ranked: DataFrame, truth: DataFrame | Classes, queries: DataFrame, copies: DataFrame | None = None) -> DataFrame:
    return _mean(average_precision(ranked, truth, queries), "ap", copies).withColumnRenamed("mean", "map")


def max_f1(ranked: DataFrame, truth: DataFrame | Classes, queries: DataFrame | None = None) -> DataFrame:
    c = pr_curve(ranked, truth)
    total = F.col("precision") + F.col("recall")
    f1 = F.when(total > 0, F.col("precision") * F.col("recall") * 2.0 / F.nullif(total, F.lit(0.0))).otherwise(F.lit(0.0))
    best = c.groupBy("qid").agg(F.max(f1).alias("f1"))
    if queries is None:
        return best
    return queries.select("qid").distinct().join(best, "qid", "left").select("qid", F.coalesce("f1", F.lit(0.0)).alias("f1"))


def mean_max_f1(ranked: DataFrame, truth: DataFrame | Classes, queries: DataFrame, copies: DataFrame | None = None) -> DataFrame:
    return _mean(max_f1(ranked, truth, queries), "f1", copies).withColumnRenamed("mean", "mean_max_f1")


def _counted_ranks(scores: DataFrame, labels: list[str], relevant: DataFrame, digits: int) -> DataFrame:
    """qid, tid, label, rank of relevant tuples: one more than the tuples before it, counted without sorting any."""
    names = [f"v{i}" for i in range(len(labels))]
    scores = scores.select("qid", "tid", *(F.col(f"`{x}`").alias(v) for x, v in zip(labels, names, strict=True)))
    own = stored(scores.join(relevant, ["qid", "tid"]).select("qid", F.col("tid").alias("own"), *(F.col(v).alias(f"own_{v}") for v in names)))

    def before(v: str) -> Column:
        x, y = F.col(v), F.col(f"own_{v}")
        a, b = F.round(x, digits), F.round(y, digits)
        # scores that are this far apart stay so when they are rounded, which is the costly part
        apart = (F.abs(x - y) > 2.0 * 10.0**-digits) & (x != y)
        return F.when(apart, x > y).otherwise((a > b) | ((a == b) & (F.col("tid") < F.col("own"))))

    met = scores.join(own, "qid").groupBy("qid", "own").agg(*(F.count_if(before(v)).alias(v) for v in names), *(F.max(F.col(f"own_{v}").isNotNull()).alias(f"has_{v}") for v in names))
    each = (F.when(F.col(f"has_{v}"), F.struct(F.lit(x).alias("label"), (F.col(v) + 1).alias("rank"))) for x, v in zip(labels, names, strict=True))
    return met.select("qid", F.col("own").alias("tid"), F.explode(F.array_compact(F.array(*each))).alias("x")).select("qid", "tid", "x.*")


def _sorted_ranks(scores: DataFrame, labels: list[str], relevant: DataFrame, digits: int) -> DataFrame:
    """The same by sorting, for queries with many relevant tuples. Pairs below a query's worst relevant one aren't ranked."""
    names = [f"v{i}" for i in range(len(labels))]
    scores = scores.select("qid", "tid", *(F.round(F.col(f"`{x}`"), digits).alias(v) for x, v in zip(labels, names, strict=True)))
    floors = scores.join(relevant, ["qid", "tid"]).groupBy("qid").agg(*(F.min(v).alias(f"floor_{v}") for v in names))
    high = (F.when(F.col(v) >= F.col(f"floor_{v}"), F.struct(F.lit(x).alias("label"), F.col(v).alias("score"))) for x, v in zip(labels, names, strict=True))
    above = scores.join(floors, "qid").join(relevant.withColumn("rel", F.lit(1)), ["qid", "tid"], "left")
    above = above.select("qid", "tid", "rel", F.explode(F.array_compact(F.array(*high))).alias("x")).select("qid", "tid", "rel", "x.*")
    order = Window.partitionBy("label", "qid").orderBy(F.desc("score"), "tid")
    return above.withColumn("rank", F.row_number().over(order).cast("long")).where("rel = 1").select("qid", "tid", "label", "rank")


def measures(scores: DataFrame, labels: list[str], truth: DataFrame, queries: DataFrame, digits: int = 9) -> DataFrame:
    """label, map, mean_max_f1 of the score columns `labels` of scores (qid, tid). Both measures only need the ranks of
    relevant tuples: F1 falls with every other tuple."""
    relevant = truth.select("qid", "tid").distinct()
    of = stored(relevant.groupBy("qid").agg(F.count(F.lit(1)).alias("relevant")))
    many = of.where(F.col("relevant") > FEW_RELEVANT).select("qid")
    if many.isEmpty():
        ranked = _counted_ranks(scores, labels, relevant, digits)
    else:
        few = of.where(F.col("relevant") <= FEW_RELEVANT).select("qid")
        ranked = _counted_ranks(scores, labels, relevant.join(few, "qid", "left_semi"), digits)
        ranked = ranked.unionByName(_sorted_ranks(scores, labels, relevant.join(many, "qid", "left_semi"), digits))
    order = Window.partitionBy("qid", "label").orderBy("rank")
    ranked = ranked.withColumn("hits", F.row_number().over(order).cast("double")).join(of, "qid")
    p, r = F.col("hits") / F.col("rank"), F.col("hits") / F.col("relevant")
    per = ranked.groupBy("qid", "label").agg((F.sum(p) / F.max("relevant")).alias("ap"), F.max(p * r * 2.0 / (p + r)).alias("f1"))
    every = queries.select("qid").distinct().select("qid", F.explode(F.array(*map(F.lit, labels))).alias("label"))
    return every.join(per, ["qid", "label"], "left").groupBy("label").agg(F.round(F.avg(F.coalesce("ap", F.lit(0.0))), 6).alias("map"), F.round(F.avg(F.coalesce("f1", F.lit(0.0))), 6).alias("mean_max_f1"))


@F.pandas_udf(DoubleType())
def average_precision_udf(rel: pd.Series, rank: pd.Series) -> float:
    """Grouped-aggregate twin of average_precision, over returned tuples only."""
    order = rel.iloc[rank.argsort()].to_numpy()
    total = order.sum()
    return float((order.cumsum() / np.arange(1, len(order) + 1) * order).sum() / total) if total else 0.0


def ranks_of(ranked: DataFrame, tids: list[int]) -> DataFrame:
    return ranked.where(F.col("tid").isin(tids)).select("qid", "tid", "rank")


def idf_histogram(index: TokenIndex, bins: int = 20, rate: float | None = None) -> DataFrame:
    """bin, low, tokens, postings by idf; with rate also how many of them that pruning rate would drop."""
    m = index.meta
    value = weights.idf(index.n(), F.col("df"))
    width = max((m.max_idf - m.min_idf) / bins, 1e-12)
    place = F.least(F.floor((value - m.min_idf) / width + 1e-9), F.lit(bins - 1)).cast("int")
    out = index.stats.withColumn("bin", place).withColumn("idf", value)
    cut = m.min_idf + (rate or 0.0) * (m.max_idf - m.min_idf)
    extra = [F.sum(F.when(F.col("idf") < cut - 1e-12, F.col("df")).otherwise(F.lit(0))).alias("dropped")] if rate is not None else []
    return out.groupBy("bin").agg(F.count(F.lit(1)).alias("tokens"), F.sum("df").alias("postings"), *extra).withColumn("low", F.col("bin") * width + m.min_idf)


def filter_report(candidates: DataFrame, exact: DataFrame, pairs: int) -> dict[str, float]:
    """Candidates as a share of all pairs, and exact results (qid, tid) that the filter missed."""
    c = candidates.select("qid", "tid").distinct()
    n = c.count()
    missed = exact.select("qid", "tid").join(c, ["qid", "tid"], "left_anti").count()
    return {"candidates": n, "share": n / pairs if pairs else 0.0, "missed": missed}


def timed(make: Callable[[], DataFrame]) -> float:
    """Wall seconds to compute a frame and throw it away."""
    start = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start
