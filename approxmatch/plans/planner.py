"""Choices above the DataFrame API that the optimiser can't make: layout, filter, and whether a join is feasible."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.index import MOST_BROADCAST, Queries, TokenIndex, query_tokens

#: Predicates with a per-tuple sum that needs the whole bag; the others only need shared tokens.
TUPLE_SUMS = ("wj", "cosine", "lm", "soft_tfidf")


@dataclass(frozen=True)
class Plan:
    layout: str
    broadcast_queries: bool
    touched: float  # postings that the queries' tokens have
    scanned: float  # tokens that a row-local pass looks at
    reason: str


def touched_postings(index: TokenIndex, queries: Queries) -> int:
    """Sum of the document frequencies of the queries' tokens."""
    return query_tokens(index, queries).agg(F.coalesce(F.sum("df"), F.lit(0))).first()[0]


def choose_plan(index: TokenIndex, queries, predicate: str = "bm25", threshold: float | None = None, k: int | None = None) -> Plan:
    """Row-local where the queries' tokens stand in more postings than one pass over the bags for each query has
    tokens, or where the queries are few and their tokens frequent; postings otherwise."""
    q = Queries.of(index.rows.sparkSession, queries)
    n = q.rows if q.rows is not None else q.frame.count()
    if n > MOST_BROADCAST and threshold is None and k is None:
        raise ValueError("so many queries without a threshold or k are close to a cross product")
    touched, scanned = float(touched_postings(index, Queries(q.frame, n))), float(index.meta.cs) * max(n, 1)
    if n <= 64 and touched > 0.5 * scanned:
        return Plan("row", True, touched, scanned, "most tokens are touched anyway: a pass without a shuffle")
    return Plan("posting", n <= MOST_BROADCAST, touched, scanned, "few postings are touched")


def explain(df: DataFrame) -> str:
    """The physical plan as text."""
    return df._jdf.queryExecution().toString()
