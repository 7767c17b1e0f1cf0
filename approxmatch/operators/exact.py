"""Brute force: every tuple against every query, row by row, without postings, filters or candidates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import combo, edit, ranking, scoring
from .index import Queries, TokenIndex, broadcast_up_to


def score_all(index: TokenIndex, queries, predicate: str, **params) -> DataFrame:
    """qid, tid, score of all pairs: what the faster ways must agree with, and full rank lists."""
    q = Queries.of(index.rows.sparkSession, queries)
    if predicate == "edit":
        return edit.score_edit(index.rows.select("tid", "s"), q, **params)
    if predicate == "ges":
        return combo.score_ges(index, q, **params)
    if predicate == "ges_bound":
        return combo.score_ges_bound(index, q, candidates="all", **params)
    if predicate == "soft_tfidf":
        found = combo.score_soft_tfidf(index, q, **params)
        every = index.rows.select("tid").crossJoin(broadcast_up_to(q.frame.select("qid"), q.rows))
        return every.join(found, ["qid", "tid"], "left").select("qid", "tid", F.coalesce("score", F.lit(0.0)).alias("score"))
    if predicate not in ("xect", "jaccard", "wm", "wj", "cosine", "bm25", "lm", "hmm"):
        raise ValueError(f"unknown predicate {predicate!r}; one of {', '.join(ranking.PREDICATES)}")
    return getattr(scoring, f"score_{predicate}")(index, q, layout="row", candidates="all", **params)
