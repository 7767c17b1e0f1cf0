"""Edit similarity: brute force, other cost models, and selection through a loss-free gram filter."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import strsim, text
from .index import Queries, broadcast_up_to


def _pairs(rel: DataFrame, q: Queries) -> DataFrame:
    return rel.select("tid", F.col("s").alias("d")).crossJoin(broadcast_up_to(q.frame.select("qid", F.col("s").alias("q")), q.rows))


def score_edit(rel: DataFrame, queries, costs: dict[str, float] | None = None) -> DataFrame:
    """1 - cost / longer length of every pair; costs (insert, delete, substitute, swap) other than 1 run as a UDF."""
    q = Queries.of(rel.sparkSession, queries)
    pairs = _pairs(rel, q).where("d is not null and q is not null")
    if costs is None:
        return pairs.select("qid", "tid", strsim.edit_similarity(F.col("q"), F.col("d")).alias("score"))
    cost = strsim.weighted_edit_distance(F.col("q"), F.col("d"), **costs)
    longer = F.greatest(F.length("q"), F.length("d"))
    return pairs.select("qid", "tid", F.when(longer == 0, F.lit(1.0)).otherwise(1.0 - cost / F.greatest(longer, F.lit(1))).alias("score"))


def most_edits(longer: Column, theta: float) -> Column:
    return F.floor(longer * (1.0 - theta) + 1e-9).cast("int")


def edit_candidates(rel: DataFrame, queries, theta: float = 0.7, q: int = 2, positional: bool = True) -> DataFrame:
    """qid, tid, d, q: pairs that may reach theta, none missing.

    Within k edits two strings differ by at most k in length and share, as bags, at least longer + q - 1 - k q of
    their end-padded grams, in places at most k apart. Where that bound isn't positive (possible only if
    q (1 - theta) > 1) the length alone decides.
    """
    queries = Queries.of(rel.sparkSession, queries)
    base = rel.where("s is not null").withColumn("g", text.edit_grams(F.col("s"), q))
    asked = queries.frame.where("s is not null").withColumn("g", text.edit_grams(F.col("s"), q))
    longer = F.greatest(F.length("d"), F.length("q"))
    k = most_edits(longer, theta)
    length_ok = F.abs(F.length("d") - F.length("q")) <= k
    least = longer + (q - 1) - k * q
    if positional:
        a = asked.select("qid", F.length("s").alias("lq"), F.posexplode("g").alias("pq", "token"))
        lengths = base.select("tid", F.length("s").alias("ld"), F.posexplode("g").alias("pd", "token"))
        apart = F.abs(F.col("pd") - F.col("pq")) <= most_edits(F.greatest("ld", "lq"), theta)
        near = lengths.join(broadcast_up_to(a, queries.rows), "token").where(apart & (F.abs(F.col("ld") - F.col("lq")) <= most_edits(F.greatest("ld", "lq"), theta)))
        met = near.groupBy("qid", "tid").agg(F.least(F.size(F.collect_set("pd")), F.size(F.collect_set("pq"))).alias("shared"))
    else:
        b = base.select("tid", F.explode(text.token_bag(F.col("g"))).alias("x")).select("tid", "x.token", "x.tf")
        a = asked.select("qid", F.explode(text.token_bag(F.col("g"))).alias("x")).select("qid", "x.token", F.col("x.tf").alias("qtf"))
        met = b.join(broadcast_up_to(a, queries.rows), "token").groupBy("qid", "tid").agg(F.sum(F.least("tf", "qtf")).alias("shared"))
    strings = met.join(rel.select("tid", F.col("s").alias("d")), "tid").join(broadcast_up_to(queries.frame.select("qid", F.col("s").alias("q")), queries.rows), "qid")
    out = strings.where(length_ok & (F.col("shared") >= least)).select("qid", "tid", "d", "q")
    if q * (1.0 - theta) <= 1.0:
        return out
    free = _pairs(rel, queries).where(length_ok & (least <= 0)).select("qid", "tid", "d", "q")
    return out.unionByName(free).distinct()


def edit_select(rel: DataFrame, queries, theta: float = 0.7, q: int = 2, positional: bool = True, costs: dict[str, float] | None = None) -> DataFrame:
    """Pairs with edit similarity of at least theta. Other cost models are verified without the gram filter when one
    of their costs is below 1, as the filter counts unit edits."""
    if costs is not None and min(v for v in costs.values() if v is not None) < 1.0:
        return score_edit(rel, queries, costs).where(F.col("score") >= theta - 1e-12)
    pairs = edit_candidates(rel, queries, theta, q, positional)
    longer = F.greatest(F.length("d"), F.length("q"))
    if costs is not None:
        score = 1.0 - strsim.weighted_edit_distance(F.col("q"), F.col("d"), **costs) / F.greatest(longer, F.lit(1))
        return pairs.withColumn("score", score).where(F.col("score") >= theta - 1e-12).select("qid", "tid", "score")
    near = pairs.withColumn("away", F.levenshtein("d", "q"))
    near = near.where((F.col("away") >= 0) & (F.col("away") <= most_edits(longer, theta)))
    return near.select("qid", "tid", (1.0 - F.col("away").cast("double") / F.greatest(longer, F.lit(1))).alias("score"))
