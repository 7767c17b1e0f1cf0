"""Combination predicates over words: generalised edit similarity with its upper-bound filters, and SoftTFIDF.

Word similarities are computed between *different* words only (the query's against the vocabulary), then joined
back to the tuples that hold them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import minhash, strsim, text, weights
from .index import Queries, TokenIndex, broadcast_up_to
from .storage import dealt, spread, stored


def _words(queries: Queries, case: str = "none") -> DataFrame:
    s = F.lower("s") if case == "lower" else F.col("s")
    return queries.frame.select("qid", F.posexplode(text.words(s)).alias("pos", "word"))


def query_word_idf(index: TokenIndex, queries: Queries, unseen: str = "average") -> DataFrame:
    """qid, pos, word, w: idf of the query's words; the mean over the vocabulary (or 0, "drop") for unseen ones."""
    known = index.stats.select(F.col("token").alias("word"), weights.idf(index.n(), F.col("df")).alias("w"))
    rest = index.meta.mean_idf if unseen == "average" else 0.0
    asked = _words(queries, index.spec.case)
    few = known.join(broadcast_up_to(asked.select("word").distinct(), queries.tokens), "word", "left_semi")
    return asked.join(few, "word", "left").withColumn("w", F.coalesce("w", F.lit(rest)))


def _weighted_lists(index: TokenIndex, tids: DataFrame | None = None) -> DataFrame:
    """tid, dwords: array<struct<word, w>> in order."""
    rows = index.rows if tids is None else index.rows.join(tids.select("tid").distinct(), "tid", "left_semi")
    s = F.lower("s") if index.spec.case == "lower" else F.col("s")
    each = rows.select("tid", F.posexplode(text.words(s)).alias("pos", "token"))
    each = each.join(broadcast_up_to(index.stats.select("token", weights.idf(index.n(), F.col("df")).alias("w")), index.meta.vocabulary), "token")
    lists = dealt(each, "tid").groupBy("tid").agg(F.array_sort(F.collect_list(F.struct("pos", "token", "w"))).alias("x"))
    return lists.select("tid", F.transform("x", lambda x: F.struct(x["token"].alias("word"), x["w"].alias("w"))).alias("dwords"))


def _query_lists(index: TokenIndex, queries: Queries, unseen: str) -> DataFrame:
    each = query_word_idf(index, queries, unseen)
    lists = each.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("pos", "word", "w"))).alias("x"))
    return lists.select("qid", F.transform("x", lambda x: F.struct(x["word"].alias("word"), x["w"].alias("w"))).alias("qwords"))


def score_ges(index: TokenIndex, queries, c_ins: float = 0.5, unseen: str = "average", pairs: DataFrame | None = None, native: bool = True) -> DataFrame:
    """Generalised edit similarity of every pair, or of `pairs` (qid, tid). The index holds words."""
    q = Queries.of(index.rows.sparkSession, queries)
    asked = _query_lists(index, q, unseen)
    lists = _weighted_lists(index, pairs)
    if pairs is None:
        both = lists.crossJoin(broadcast_up_to(asked, q.rows))
    else:
        both = dealt(pairs.select("qid", "tid").join(lists, "tid"), "qid", "tid").join(broadcast_up_to(asked, q.rows), "qid")
    f = strsim.generalised_edit_similarity if native else strsim.ges_udf
    return both.select("qid", "tid", f(F.col("qwords"), F.col("dwords"), c_ins).alias("score"))


def word_pairs(index: TokenIndex, asked: DataFrame, rows: int | None, sim: str, q: int = 2, hashes: int = 5, seed: int = 42, grams: str = "set", above: float | None = None) -> DataFrame:
    """qword, word, sim of the query's words and the vocabulary, for pairs that share a gram or a hash; for edit and
    Jaro-Winkler all pairs, or those that can be above `above`, by native bounds of length and letters."""
    vocabulary = spread(index.stats.select(F.col("token").alias("word")))
    mine = asked.select(F.col("word").alias("qword")).distinct()
    if sim in ("jaccard", "intersect"):
        bag = text.token_bag(text.qgrams(F.col("x"), q))

        def exploded(df: DataFrame, name: str, size: str) -> DataFrame:
            b = df.withColumn("x", F.col(name)).withColumn("b", bag)
            n = F.aggregate("b", F.lit(0), lambda t, x: t + x["tf"]) if grams == "bag" else F.size("b")
            return b.select(name, n.alias(size), F.explode("b").alias("g")).select(name, size, "g.token", F.col("g.tf").alias(f"tf_{size}"))

        a, b = exploded(mine, "qword", "n1"), exploded(vocabulary, "word", "n2")
        both = F.least("tf_n1", "tf_n2") if grams == "bag" else F.lit(1)
        met = b.join(broadcast_up_to(a, rows), "token").groupBy("qword", "word").agg(F.sum(both).cast("double").alias("n"), F.max("n1").alias("n1"), F.max("n2").alias("n2"))
        return met.select("qword", "word", (F.col("n") / (F.col("n1") + F.col("n2") - F.col("n")) if sim == "jaccard" else F.col("n")).alias("sim"))
    if sim == "minhash":
        def signed(df: DataFrame, name: str) -> DataFrame:
            return df.select(name, F.posexplode(minhash.minhash_signature(F.array_distinct(text.qgrams(F.col(name), q)), hashes, seed)).alias("fid", "value"))

        met = signed(vocabulary, "word").join(broadcast_up_to(signed(mine, "qword"), rows), ["fid", "value"])
        return met.groupBy("qword", "word").agg((F.count(F.lit(1)) / F.lit(float(hashes))).alias("sim"))
    if above is not None and sim == "jaro_winkler":
        vocabulary = vocabulary.withColumn("mask", strsim.letter_mask(F.col("word")))
        mine = mine.withColumn("qmask", strsim.letter_mask(F.col("qword")))
    pairs = vocabulary.crossJoin(broadcast_up_to(mine, rows))
    if above is not None and sim == "jaro_winkler":
        pairs = pairs.where(strsim.jaro_winkler_mask_bound(F.col("qword"), F.col("word"), F.col("qmask"), F.col("mask")) > above - 1e-9)
        pairs = pairs.where(strsim.jaro_winkler_bound(F.col("qword"), F.col("word")) > above - 1e-9)
    if above is not None and sim == "edit":
        longer = F.greatest(F.length("qword"), F.length("word"))
        pairs = pairs.where(F.abs(F.length("qword") - F.length("word")) <= longer * (1.0 - above) + 1e-9)
    f = {"edit": strsim.edit_similarity, "jaro_winkler": strsim.jaro_winkler, "jaro": strsim.jaro}[sim]
    return pairs.select("qword", "word", f(F.col("qword"), F.col("word")).alias("sim"))


def score_ges_bound(index: TokenIndex, queries, sim: str = "jaccard", q: int = 2, hashes: int = 5, grams: str = "set", unseen: str = "average", seed: int = 42, candidates: str = "matching") -> DataFrame:
    """Upper-bound score of the generalised edit similarity: the order of words is free, and a query word's edit
    similarity to its best word is bounded by its gram similarity (2 / q) sim + 1 - 1 / q.

    The part 1 - 1 / q doesn't depend on the tuple, so it also stands for query words without a shared gram; tuples
    without any score exactly that, and only candidates="all" returns them. The score isn't clamped at 1.
    grams="bag" bounds without loss; sets of grams of very repetitive words can fall short."""
    qs = Queries.of(index.rows.sparkSession, queries)
    asked = query_word_idf(index, qs, unseen)
    total = asked.groupBy("qid").agg(F.sum("w").alias("total"))
    sims = word_pairs(index, asked, qs.tokens, sim, q, hashes, seed, grams)
    held = index.postings.select("tid", F.col("token").alias("word"))
    weighed = asked.join(total, "qid").select("qid", "pos", F.col("word").alias("qword"), (F.col("w") / F.nullif("total", F.lit(0.0))).alias("share"))
    reach = sims.join(broadcast_up_to(weighed, qs.tokens), "qword")
    best = held.join(reach, "word").groupBy("qid", "tid", "pos").agg(F.max("sim").alias("sim"), F.max("share").alias("share"))
    scored = best.groupBy("qid", "tid").agg((F.sum(F.col("share") * F.col("sim")) * (2.0 / q) + (1.0 - 1.0 / q)).alias("score"))
    if candidates == "matching":
        return scored
    every = index.rows.select("tid").crossJoin(broadcast_up_to(qs.frame.select("qid"), qs.rows))
    return every.join(scored, ["qid", "tid"], "left").select("qid", "tid", F.coalesce("score", F.lit(1.0 - 1.0 / q)).alias("score"))


def ges_select(index: TokenIndex, queries, theta: float = 0.8, filter: str = "jaccard", q: int = 2, c_ins: float = 0.5, unseen: str = "average", keep_candidates: bool = False, **bound) -> DataFrame:  # noqa: A002
    """Exact generalised edit similarity of the pairs whose bound reaches theta, and which reach it themselves
    (all candidates with keep_candidates). For theta <= 1 - 1 / q the bound rules nothing out and isn't used."""
    if filter == "none" or theta <= 1.0 - 1.0 / q:
        scored = score_ges(index, queries, c_ins, unseen)
    else:
        found = score_ges_bound(index, queries, filter, q, unseen=unseen, **bound).where(F.col("score") >= theta - 1e-12)
        scored = score_ges(index, queries, c_ins, unseen, pairs=stored(found.select("qid", "tid")))
    return scored if keep_candidates else scored.where(F.col("score") >= theta - 1e-12)


def score_soft_tfidf(index: TokenIndex, queries, word_sim: str = "jaro_winkler", theta: float = 0.8, unseen: str = "average", **options) -> DataFrame:
    """tf-idf cosine in which a query word meets its most similar word of the tuple, if that is above theta
    (strictly). Of equally similar words the first in order counts."""
    qs = Queries.of(index.rows.sparkSession, queries)
    asked = query_word_idf(index, qs, unseen).groupBy("qid", "word").agg((F.count(F.lit(1)) * F.max("w")).alias("w"))
    norm = F.sqrt(F.sum(F.col("w") * F.col("w")).over(Window.partitionBy("qid")))
    asked = asked.withColumn("wq", F.coalesce(F.col("w") / F.nullif(norm, F.lit(0.0)), F.lit(0.0)))
    sims = word_pairs(index, asked, qs.tokens, word_sim, above=theta, **options).where(F.col("sim") > theta)
    reach = sims.join(broadcast_up_to(asked.select("qid", F.col("word").alias("qword"), "wq"), qs.tokens), "qword")
    idf = weights.idf(index.n(), F.col("df"))
    own = index.with_stats().select("tid", F.col("token").alias("word"), (F.col("tf") * idf).alias("wd"))
    norms = own.groupBy("tid").agg(F.sqrt(F.sum(F.col("wd") * F.col("wd"))).alias("norm"))
    met = own.join(reach, "word")
    best = met.groupBy("qid", "tid", "qword").agg(F.max("wq").alias("wq"), F.min(F.struct(-F.col("sim"), "word", "wd", "sim")).alias("best"))
    scored = best.groupBy("qid", "tid").agg(F.sum(F.col("wq") * F.col("best.wd") * F.col("best.sim")).alias("sum"))
    return scored.join(norms, "tid").select("qid", "tid", F.coalesce(F.col("sum") / F.nullif("norm", F.lit(0.0)), F.lit(0.0)).alias("score"))


def best_words(similar: DataFrame) -> DataFrame:
    """The most similar word of each (qid, tid, qword), the first of equals: qid, tid, qword, word, sim."""
    best = similar.groupBy("qid", "tid", "qword").agg(F.min(F.struct((-F.col("sim")).alias("away"), F.col("word").alias("word"))).alias("b"))
    return best.select("qid", "tid", "qword", F.col("b.word").alias("word"), (-F.col("b.away")).alias("sim"))


__all__ = ["Column", "best_words", "ges_select", "query_word_idf", "score_ges", "score_ges_bound", "score_soft_tfidf", "word_pairs"]
