"""Base relations and token indexes.

An index is row-local: one row per tuple with its distinct tokens and their counts, nothing exploded at rest. All
weights are functions of (tf, dl) and of a token's statistics, and at query time those ride along with the query's
few tokens, so that the large side is scanned once and joined with something small. Only what needs every token of a
tuple (norms, sums of weights) is aggregated per tuple.
"""

from __future__ import annotations

import json
from collections.abc import Iterable
from dataclasses import asdict, dataclass, field, replace
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import text, weights
from .storage import spread, stored

#: Tokens up to which pruning looks for a tuple's tokens among the dropped ones in the row itself.
FEW_DROPPED = 256
#: Rows up to which a frame is broadcast. Query frames of known size and vocabularies are checked against it.
MOST_BROADCAST = 200_000


def broadcast_up_to(df: DataFrame, rows: int | None, most: int = MOST_BROADCAST) -> DataFrame:
    """df with a broadcast hint if its number of rows is known and small; else as it is."""
    return F.broadcast(df) if rows is not None and rows <= most else df


def relation(df: DataFrame, id_col: str, str_col: str | Column) -> DataFrame:
    """tid BIGINT, s STRING: the form that every operator takes. Duplicate strings stay separate tuples."""
    s = F.col(str_col) if isinstance(str_col, str) else str_col
    out = df.select(F.col(id_col).cast("long").alias("tid"), s.alias("s"))
    if dict(out.dtypes)["s"] != "string":
        raise TypeError(f"{str_col} isn't a string column")
    return out


@dataclass(frozen=True)
class TokenSpec:
    kind: str = "qgram"
    q: int = 2
    pad: str = text.PAD
    case: str = "none"

    def tokens(self, col: Column) -> Column:
        return text.tokens(col, self.kind, self.q, self.pad, self.case)


@dataclass(frozen=True)
class IndexMeta:
    """Scalars of the collection; the only numbers of it that reach the driver."""

    n: int
    cs: int
    vocabulary: int
    mean_idf: float
    min_idf: float
    max_idf: float
    threshold: float | None = None

    @property
    def avgdl(self) -> float:
        return self.cs / self.n if self.n else 0.0


@dataclass(frozen=True)
class Queries:
    """qid BIGINT, s STRING, the number of rows where it is known, and a bound of their tokens where one is."""

    frame: DataFrame
    rows: int | None = None
    chars: int | None = None

    @cached_property
    def tokens(self) -> int | None:
        """No more tokens than this: what a broadcast of tokens is checked against."""
        if self.chars is None and (self.rows is None or self.rows > MOST_BROADCAST):
            return None
        n = self.chars if self.chars is not None else self.frame.agg(F.coalesce(F.sum(F.length("s")), F.lit(0))).first()[0]
        return n + 8 * (self.rows or 0)

    @classmethod
    def of(cls, spark: SparkSession, queries: str | Iterable[tuple[int, str]] | DataFrame | Queries) -> Queries:
        if isinstance(queries, Queries):
            return queries
        if isinstance(queries, DataFrame):
            return cls(queries.select(F.col("qid").cast("long").alias("qid"), "s"))
        rows = [(1, queries)] if isinstance(queries, str) else [(int(i), s) for i, s in queries]
        return cls(spark.createDataFrame(rows, "qid long, s string"), len(rows), 2 * sum(len(s or "") for _, s in rows))


def tokenized(rel: DataFrame, spec: TokenSpec) -> DataFrame:
    """tid, s, bag, len (distinct tokens), dl (tokens)."""
    rows = rel.withColumn("bag", text.token_bag(spec.tokens(F.col("s"))))
    return sized(rows)


def sized(rows: DataFrame) -> DataFrame:
    total = F.aggregate("bag", F.lit(0).cast("long"), lambda t, x: t + x["tf"])
    return rows.withColumn("len", F.size("bag").cast("long")).withColumn("dl", total)


def term_stats(rows: DataFrame) -> DataFrame:
    """token, df, cf, sum_pml: one aggregation, combined within tasks before the shuffle."""
    postings = rows.select("dl", F.explode("bag").alias("x")).select("x.token", "x.tf", "dl")
    return postings.groupBy("token").agg(F.count(F.lit(1)).alias("df"), F.sum("tf").cast("long").alias("cf"), F.sum(weights.p_ml(F.col("tf"), F.col("dl"))).alias("sum_pml"))


def collection_stats(rows: DataFrame, stats: DataFrame) -> IndexMeta:
    r = rows.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("dl"), F.lit(0)).alias("cs")).first()
    value = weights.idf(F.lit(float(r["n"] or 1)), F.col("df"))
    t = stats.agg(F.count(F.lit(1)).alias("v"), F.avg(value).alias("mean"), F.min(value).alias("min"), F.max(value).alias("max")).first()
    return IndexMeta(r["n"], r["cs"], t["v"], t["mean"] or 0.0, t["min"] or 0.0, t["max"] or 0.0)


@dataclass(frozen=True)
class TokenIndex:
    spec: TokenSpec
    rows: DataFrame
    stats: DataFrame
    meta: IndexMeta
    dropped: DataFrame | None = None  # tokens that pruning took out

    @classmethod
    def build(cls, rel: DataFrame, spec: TokenSpec = TokenSpec(), prune_rate: float = 0.0, path: str | None = None, strings: bool = True) -> TokenIndex:  # noqa: B008
        """Strings are tokenised once: rows and statistics are stored, and every scorer reads them. With strings=False the
        strings themselves aren't stored again (s is null), for what needs only tokens."""
        rows = tokenized(spread(rel), spec)
        rows = stored(rows if strings else rows.withColumn("s", F.lit(None).cast("string")), path and f"{path}/rows")
        stats = stored(term_stats(rows), path and f"{path}/stats")
        index = cls(spec, rows, stats, collection_stats(rows, stats))
        return index.pruned(prune_rate) if prune_rate else index

    def pruned(self, rate: float) -> TokenIndex:
        """Without the tokens whose idf is below min + rate * (max - min); every weight follows from what stays.

        A dropped token stands in more than N * exp(-threshold) tuples, so at most avgdl * exp(threshold) of them
        exist. A few are looked for in the row; more by a hash join of the postings."""
        m = self.meta
        threshold = m.min_idf + rate * (m.max_idf - m.min_idf)
        low = stored(self.stats.where(weights.idf(F.lit(float(m.n or 1)), F.col("df")) < threshold - 1e-12).select("token"))
        n = low.count()
        if n <= FEW_DROPPED:
            gone = low.agg(F.collect_set("token").alias("gone"))
            rows = self.rows.select("tid", "s", "bag").crossJoin(F.broadcast(gone)).withColumn("bag", F.filter("bag", lambda x: ~F.array_contains("gone", x["token"]))).drop("gone")
        else:
            kept = self.postings.select("tid", "token", "tf").join(broadcast_up_to(low, n), "token", "left_anti")
            bags = kept.groupBy("tid").agg(F.array_sort(F.collect_list(F.struct("token", "tf"))).alias("bag"))
            rows = self.rows.select("tid", "s").join(bags, "tid", "left").withColumn("bag", F.coalesce("bag", F.array().cast("array<struct<token:string,tf:int>>")))
        rows = stored(sized(rows))
        stats = stored(term_stats(rows))
        return TokenIndex(self.spec, rows, stats, replace(collection_stats(rows, stats), threshold=threshold), low)

    def append(self, rel: DataFrame) -> TokenIndex:
        """With further tuples. Statistics are sums, so only the new tuples are tokenised."""
        new = tokenized(rel, self.spec)
        more = term_stats(new)
        stats = self.stats.unionByName(more).groupBy("token").agg(F.sum("df").alias("df"), F.sum("cf").alias("cf"), F.sum("sum_pml").alias("sum_pml"))
        rows = self.rows.unionByName(new)
        return TokenIndex(self.spec, rows, stats, collection_stats(rows, stats))

    _sums: dict[str, DataFrame] = field(default_factory=dict, init=False, repr=False, compare=False)

    def tuple_sums(self, **sums: Column) -> DataFrame:
        """tid and sums over all tokens of a tuple, of expressions of tf, dl and the token's statistics: a weighting's
        part of the preprocessing, stored when it is first asked for."""
        key = str(sorted((name, str(c)) for name, c in sums.items()))
        if key not in self._sums:
            self._sums[key] = stored(self.with_stats().groupBy("tid").agg(*(F.sum(c).alias(name) for name, c in sums.items())))
        return self._sums[key]

    @cached_property
    def postings(self) -> DataFrame:
        """tid, token, tf, dl, len: the exploded view."""
        return self.rows.select("tid", "dl", "len", F.explode("bag").alias("x")).select("tid", "x.token", "x.tf", "dl", "len")

    def with_stats(self) -> DataFrame:
        return self.postings.join(broadcast_up_to(self.stats, self.meta.vocabulary), "token")

    def n(self) -> Column:
        return F.lit(float(self.meta.n))

    def cs(self) -> Column:
        return F.lit(float(self.meta.cs))

    # ---- storage ---------------------------------------------------------------------------------------

    def save(self, path: str, layout: str = "row", partitions: int | None = None) -> None:
        """Parquet of rows or postings, of statistics, and a JSON line. Postings are range-partitioned and sorted
        by token, so that a token's row groups are found by their statistics."""
        if layout not in ("row", "posting"):
            raise ValueError(f"unknown layout {layout!r}")
        self.rows.write.mode("overwrite").parquet(f"{path}/rows")
        if layout == "posting":
            p = self.postings
            p = p.repartitionByRange(partitions, "token", "tid") if partitions else p.repartitionByRange("token", "tid")
            p.sortWithinPartitions("token", "tid").write.mode("overwrite").parquet(f"{path}/postings")
        self.stats.write.mode("overwrite").parquet(f"{path}/stats")
        if self.dropped is not None:
            self.dropped.write.mode("overwrite").parquet(f"{path}/dropped")
        line = json.dumps({"spec": asdict(self.spec), "meta": asdict(self.meta), "layout": layout})
        self.rows.sparkSession.createDataFrame([(line,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> TokenIndex:
        line = json.loads(spark.read.text(f"{path}/meta").first()["value"])
        index = cls(TokenSpec(**line["spec"]), spark.read.parquet(f"{path}/rows"), spark.read.parquet(f"{path}/stats"), IndexMeta(**line["meta"]), spark.read.parquet(f"{path}/dropped") if line["meta"]["threshold"] is not None else None)
        if line["layout"] == "posting":
            index.__dict__["postings"] = spark.read.parquet(f"{path}/postings")
        return index


def query_tokens(index: TokenIndex, queries: Queries) -> DataFrame:
    """qid, token, qtf, qlen, qdl, df, cf, sum_pml of the query's distinct tokens; statistics are null for tokens
    that no tuple holds. After pruning, tokens below the threshold are dropped here as well."""
    rows = sized(queries.frame.withColumn("bag", text.token_bag(index.spec.tokens(F.col("s")))))
    terms = rows.select("qid", F.explode("bag").alias("x")).select("qid", "x.token", F.col("x.tf").alias("qtf"))
    known = index.stats.join(broadcast_up_to(terms.select("token").distinct(), queries.tokens), "token", "left_semi")
    terms = terms.join(broadcast_up_to(known, queries.tokens), "token", "left")
    if index.dropped is not None:
        terms = terms.join(index.dropped, "token", "left_anti")
    own = Window.partitionBy("qid")
    return terms.withColumn("qlen", F.count(F.lit(1)).over(own)).withColumn("qdl", F.sum("qtf").over(own).cast("long"))


def sample_queries(rel: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """n tuples as queries (qid = tid), by a hash order that any engine repeats."""
    return rel.orderBy(F.md5(F.concat(F.lit(f"{seed}|"), F.col("tid").cast("string")).cast("binary")), "tid").limit(n).select(F.col("tid").alias("qid"), "s")
