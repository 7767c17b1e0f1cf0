"""Token predicates: overlap, aggregate weighted, language models. Each returns qid, tid, score.

All are one shape: a sum over shared tokens of a term of (tf, dl, the token's statistics, the query's count), then an
expression of that sum with quantities of the tuple and of the query. `_sums` runs the sum in either layout:

* posting: tokens of the tuples meet the query's tokens in a hash join, sums are combined within tasks;
* row: each tuple meets each query's map of tokens and sums over its own bag, without any shuffle;
* query: the queries' tokens are dealt out by query and meet the broadcast tokens of the tuples, so that sums and ranks of
  a query stay in its task: for many queries against tuples of few tokens.

candidates="all" also returns the tuples that share no token, with the score that the formula gives them.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import weights
from ..functions.text import let
from .index import Queries, TokenIndex, broadcast_up_to, query_tokens

Term = Callable[[dict[str, Column]], Column]

LAYOUTS = ("posting", "row", "query")
#: Predicates over shared tokens, which take a layout.
TOKEN_PREDICATES = ("xect", "jaccard", "wm", "wj", "cosine", "bm25", "lm", "hmm")
#: Queries of a task in the layout "query".
QUERIES_A_TASK = 64


def _columns(prefix: str = "") -> dict[str, Column]:
    return {c: F.col(prefix + c) for c in ("tf", "dl", "qtf", "df", "cf", "sum_pml")}


def _sums(index: TokenIndex, terms: DataFrame, queries: Queries, named: dict[str, Term], layout: str, keep: tuple[str, ...] = ()) -> DataFrame:
    """qid, tid, the named sums, n_shared and the kept query columns (constant in a query)."""
    if layout not in LAYOUTS:
        raise ValueError(f"unknown layout {layout!r}")
    seen = terms.where("df is not null")
    if layout != "row":
        if layout == "query":
            spark = index.rows.sparkSession
            n = queries.rows if queries.rows is not None else queries.frame.count()
            parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), n // QUERIES_A_TASK + 1)
            met = seen.repartition(parts, "qid").join(F.broadcast(index.postings), "token")
        else:
            met = index.postings.join(broadcast_up_to(seen, queries.tokens), "token")
        sums = [F.sum(term(_columns())).alias(name) for name, term in named.items()]
        # max of a constant: carries query and tuple columns through the aggregate without widening its key
        return met.groupBy("qid", "tid").agg(*sums, F.count(F.lit(1)).alias("n_shared"), F.max("len").alias("len"), F.max("dl").alias("dl"), *(F.max(c).alias(c) for c in keep))
    per = seen.groupBy("qid").agg(F.map_from_entries(F.collect_list(F.struct("token", F.struct("qtf", "df", "cf", "sum_pml")))).alias("qmap"), *(F.max(c).alias(c) for c in keep))
    rows = index.rows.crossJoin(broadcast_up_to(per, queries.tokens))
    start = F.struct(*(F.lit(0.0).alias(name) for name in named), F.lit(0).cast("long").alias("n_shared"))

    def add(acc: Column, x: Column) -> Column:
        def with_entry(e: Column) -> Column:
            values = {"tf": x["tf"], "dl": F.col("dl"), **{c: e[c] for c in ("qtf", "df", "cf", "sum_pml")}}
            return F.when(e.isNull(), acc).otherwise(F.struct(*((acc[name] + term(values)).alias(name) for name, term in named.items()), (acc["n_shared"] + 1).alias("n_shared")))

        return let(F.element_at(F.col("qmap"), x["token"]), with_entry)

    rows = rows.withColumn("sums", F.aggregate("bag", start, add)).where(F.col("sums.n_shared") > 0)
    return rows.select("qid", "tid", *(F.col(f"sums.{name}").alias(name) for name in named), "sums.n_shared", "len", "dl", *keep)


def _finish(index: TokenIndex, queries: Queries, scored: DataFrame, candidates: str, other: Column | None = None, tuples: DataFrame | None = None, per_query: DataFrame | None = None) -> DataFrame:
    if candidates == "matching":
        return scored.select("qid", "tid", "score")
    if candidates != "all":
        raise ValueError(f"unknown candidates {candidates!r}")
    every = index.rows.select("tid").crossJoin(broadcast_up_to(queries.frame.select("qid"), queries.rows))
    if tuples is not None:
        every = every.join(tuples, "tid", "left")
    if per_query is not None:
        every = every.join(per_query, "qid", "left")
    rest = every.join(scored.select("qid", "tid", F.col("score").alias("found")), ["qid", "tid"], "left")
    return rest.select("qid", "tid", F.coalesce("found", other if other is not None else F.lit(0.0)).alias("score"))


def _prepared(index: TokenIndex, queries) -> tuple[Queries, DataFrame]:
    q = Queries.of(index.rows.sparkSession, queries)
    return q, query_tokens(index, q)


def _weight(index: TokenIndex, kind: str, floor: float | None = None) -> Callable[[Column], Column]:
    if kind == "rs":
        return lambda df: weights.rs_weight(index.n(), df, floor)
    if kind == "idf":
        return lambda df: weights.idf(index.n(), df)
    raise ValueError(f"unknown weights {kind!r}")


def tuple_sums(index: TokenIndex, **sums: Column) -> DataFrame:
    """tid and sums over all tokens of a tuple, of expressions of tf, dl and the token's statistics."""
    return index.tuple_sums(**sums)


# ---- overlap --------------------------------------------------------------------------------------------


def score_xect(index: TokenIndex, queries, layout: str = "posting", candidates: str = "matching") -> DataFrame:
    """Number of shared distinct tokens."""
    q, terms = _prepared(index, queries)
    s = _sums(index, terms, q, {}, layout)
    return _finish(index, q, s.withColumn("score", F.col("n_shared").cast("double")), candidates)


def score_jaccard(index: TokenIndex, queries, layout: str = "posting", candidates: str = "matching") -> DataFrame:
    """Shared over united distinct tokens; tokens that no tuple holds count among the query's."""
    q, terms = _prepared(index, queries)
    s = _sums(index, terms, q, {}, layout, keep=("qlen",))
    return _finish(index, q, s.withColumn("score", F.col("n_shared").cast("double") / (F.col("len") + F.col("qlen") - F.col("n_shared"))), candidates)


def score_wm(index: TokenIndex, queries, weights: str = "rs", floor: float | None = None, layout: str = "posting", candidates: str = "matching") -> DataFrame:
    """Weight of the shared tokens. RS weights of tokens in more than half of the tuples are negative."""
    q, terms = _prepared(index, queries)
    w = _weight(index, weights, floor)
    s = _sums(index, terms, q, {"w": lambda x: w(x["df"])}, layout)
    return _finish(index, q, s.withColumn("score", F.col("w")), candidates)


def score_wj(index: TokenIndex, queries, weights: str = "rs", floor: float | None = None, unseen: str = "weight", layout: str = "posting", candidates: str = "matching") -> DataFrame:
    """Shared weight over united weight. Query tokens that no tuple holds weigh as df = 0 (RS) or the mean (idf),
    or nothing with unseen="drop"."""
    q, terms = _prepared(index, queries)
    w = _weight(index, weights, floor)
    new = F.lit(0.0) if unseen == "drop" else w(F.lit(0)) if weights == "rs" else F.lit(index.meta.mean_idf)
    own = terms.groupBy("qid").agg(F.sum(F.when(F.col("df").isNull(), new).otherwise(w(F.col("df")))).alias("qw"))
    terms = terms.join(own, "qid")
    s = _sums(index, terms, q, {"w": lambda x: w(x["df"])}, layout, keep=("qw",)).join(tuple_sums(index, wlen=w(F.col("df"))), "tid")
    union = F.col("wlen") + F.col("qw") - F.col("w")
    return _finish(index, q, s.withColumn("score", F.when(union != 0, F.col("w") / F.nullif(union, F.lit(0.0))).otherwise(F.lit(0.0))), candidates)


# ---- aggregate weighted -----------------------------------------------------------------------------------


def score_weighted_sum(base_weights: DataFrame, query_weights: DataFrame) -> DataFrame:
    """The family's general form: (tid, token, w) and (qid, token, w) give the sum of products over shared tokens."""
    q = query_weights.select("qid", "token", F.col("w").alias("wq"))
    return base_weights.join(q, "token").groupBy("qid", "tid").agg(F.sum(F.col("w") * F.col("wq")).alias("score"))


def score_cosine(index: TokenIndex, queries, unseen: str = "drop", layout: str = "posting", candidates: str = "matching") -> DataFrame:
    """Cosine of tf-idf vectors. Tokens that no tuple holds have no idf: dropped, or the mean with unseen="average"."""
    q, terms = _prepared(index, queries)
    idf = weights.idf(index.n(), F.col("df"))
    wq = F.col("qtf") * F.coalesce(idf, F.lit(index.meta.mean_idf if unseen == "average" else 0.0))
    terms = terms.join(terms.groupBy("qid").agg(F.sqrt(F.sum(wq * wq)).alias("qnorm")), "qid")
    own = tuple_sums(index, norm2=F.pow(F.col("tf") * idf, 2.0))
    s = _sums(index, terms, q, {"w": lambda x: x["qtf"] * x["tf"] * F.pow(weights.idf(index.n(), x["df"]), 2.0)}, layout, keep=("qnorm",)).join(own, "tid")
    norm = F.sqrt("norm2") * F.col("qnorm")
    return _finish(index, q, s.withColumn("score", F.when(norm > 0, F.col("w") / F.nullif(norm, F.lit(0.0))).otherwise(F.lit(0.0))), candidates)


def score_bm25(index: TokenIndex, queries, k1: float = 1.5, k3: float = 8.0, b: float = 0.675, floor: float | None = None, layout: str = "posting", candidates: str = "matching") -> DataFrame:
    q, terms = _prepared(index, queries)
    avgdl = F.lit(index.meta.avgdl)

    def term(x: dict[str, Column]) -> Column:
        rs = weights.rs_weight(index.n(), x["df"], floor)
        return weights.bm25_doc_weight(rs, x["tf"], x["dl"], avgdl, k1, b) * weights.bm25_query_weight(x["qtf"], k3)

    s = _sums(index, terms, q, {"score": term}, layout)
    return _finish(index, q, s, candidates)


# ---- language models ----------------------------------------------------------------------------------------


def _times(semantics: str, x: dict[str, Column]) -> Column:
    if semantics not in ("set", "bag"):
        raise ValueError(f"unknown query semantics {semantics!r}")
    return x["qtf"].cast("double") if semantics == "bag" else F.lit(1.0)


def score_lm(index: TokenIndex, queries, form: str = "restricted", query_semantics: str = "set", log: bool = False, layout: str = "posting", candidates: str = "matching") -> DataFrame:
    """Probability that the tuple's model gives the query's tokens and none other.

    "restricted" keeps the tokens of the tuple and drops what is constant in a query. "full" is the product over the
    whole vocabulary, at the same cost: ln(1 - g) of all tokens is a scalar, from which a tuple's own tokens are
    taken out per tuple. Products run over the query's set of tokens, or its bag; unknown tokens are dropped. The
    score is exp of the log score unless log is set.
    """
    if form not in ("restricted", "full"):
        raise ValueError(f"unknown form {form!r}")
    q, terms = _prepared(index, queries)
    full = form == "full"

    def term(x: dict[str, Column]) -> Column:
        p = weights.lm_prob(x["tf"], x["dl"], x["sum_pml"], x["df"])
        g = weights.background(x["cf"], index.cs())
        out = F.log(p) - F.log1p(-p) - F.log(g)
        return (out + F.log1p(-g) if full else out) * _times(query_semantics, x)

    c = _columns()
    p, g = weights.lm_prob(c["tf"], c["dl"], c["sum_pml"], c["df"]), weights.background(F.col("cf"), index.cs())
    own = tuple_sums(index, comp=F.log1p(-p) - F.log1p(-g) if full else F.log1p(-p))
    s = _sums(index, terms, q, {"w": term}, layout).join(own, "tid")
    per = queries_constant = None
    score, other = F.col("w") + F.col("comp"), F.coalesce("comp", F.lit(0.0))
    if full:
        constant = index.stats.agg(F.sum(F.log1p(-g))).first()[0] or 0.0
        times = F.col("qtf").cast("double") if query_semantics == "bag" else F.lit(1.0)
        per = terms.where("cf is not null").groupBy("qid").agg(F.sum((F.log(g) - F.log1p(-g)) * times).alias("qconst"))
        s = s.join(broadcast_up_to(per, q.rows), "qid")
        queries_constant = F.coalesce("qconst", F.lit(0.0)) + constant
        score, other = score + queries_constant, other + queries_constant
    final = (lambda x: x) if log else F.exp
    return _finish(index, q, s.withColumn("score", final(score)), candidates, final(other), own, per)


def score_hmm(index: TokenIndex, queries, a0: float = 0.2, form: str = "ratio", query_semantics: str = "set", log: bool = False, layout: str = "posting", candidates: str = "matching") -> DataFrame:
    """Two-state model: a token comes from the tuple (1 - a0) or from general text (a0).

    "ratio" divides by what is constant in a query, so that only shared tokens count; "full" keeps it. Unknown tokens
    are dropped. The ratio can exceed what a double holds for long queries: log=True gives its logarithm.
    """
    if not 0 < a0 < 1:
        raise ValueError("a0 must lie between 0 and 1")
    if form not in ("ratio", "full"):
        raise ValueError(f"unknown form {form!r}")
    q, terms = _prepared(index, queries)
    s = _sums(index, terms, q, {"w": lambda x: F.log(weights.hmm_weight(x["tf"], x["dl"], x["cf"], index.cs(), a0)) * _times(query_semantics, x)}, layout)
    score, other, per = F.col("w"), F.lit(0.0), None
    if form == "full":
        times = F.col("qtf").cast("double") if query_semantics == "bag" else F.lit(1.0)
        per = terms.where("cf is not null").groupBy("qid").agg(F.sum(F.log(weights.real(F.col("cf")) / index.cs() * a0) * times).alias("qconst"))
        s = s.join(broadcast_up_to(per, q.rows), "qid")
        score, other = score + F.col("qconst"), F.coalesce("qconst", F.lit(0.0))
    final = (lambda x: x) if log else F.exp
    return _finish(index, q, s.withColumn("score", final(score)), candidates, final(other), None, per)


# ---- several predicates in one pass ---------------------------------------------------------------------------


@dataclass(frozen=True)
class Shape:
    """A predicate as sums over shared tokens, sums over a tuple's tokens, sums over a query's tokens (whose statistics
    may be null), and the score of these by name."""

    score: Callable[[Callable[[str], Column]], Column]
    shared: dict[str, Term] = field(default_factory=dict)
    own: dict[str, Column] = field(default_factory=dict)
    asked: dict[str, Column] = field(default_factory=dict)


def _ratio(top: Column, bottom: Column) -> Column:
    return F.when(bottom != 0, top / F.nullif(bottom, F.lit(0.0))).otherwise(F.lit(0.0))


def shape(index: TokenIndex, predicate: str, **params) -> Shape:
    """The token predicates, logarithms for language models and HMM, with the defaults of the score_* functions."""
    n, df = index.n(), F.col("df")
    if predicate == "xect":
        return Shape(lambda c: F.col("n_shared").cast("double"))
    if predicate == "jaccard":
        return Shape(lambda c: F.col("n_shared").cast("double") / (F.col("len") + F.col("qlen") - F.col("n_shared")))
    if predicate in ("wm", "wj"):
        kind = params.get("weights", "rs")
        w = _weight(index, kind, params.get("floor"))
        shared = {"w": lambda x: w(x["df"])}
        if predicate == "wm":
            return Shape(lambda c: c("w"), shared)
        new = w(F.lit(0)) if kind == "rs" else F.lit(index.meta.mean_idf)
        asked = {"qw": F.sum(F.when(df.isNull(), new).otherwise(w(df)))}
        return Shape(lambda c: _ratio(c("w"), c("wlen") + c("qw") - c("w")), shared, {"wlen": w(df)}, asked)
    if predicate == "cosine":
        idf = weights.idf(n, df)
        norm = F.sqrt(F.sum(F.pow(F.col("qtf") * F.coalesce(idf, F.lit(0.0)), 2.0)))
        return Shape(lambda c: _ratio(c("w"), F.sqrt(c("norm2")) * c("qnorm")), {"w": lambda x: x["qtf"] * x["tf"] * F.pow(weights.idf(n, x["df"]), 2.0)}, {"norm2": F.pow(F.col("tf") * idf, 2.0)}, {"qnorm": norm})
    if predicate == "bm25":
        k1, k3, b, avgdl = params.get("k1", 1.5), params.get("k3", 8.0), params.get("b", 0.675), F.lit(index.meta.avgdl)
        return Shape(lambda c: c("w"), {"w": lambda x: weights.bm25_doc_weight(weights.rs_weight(n, x["df"]), x["tf"], x["dl"], avgdl, k1, b) * weights.bm25_query_weight(x["qtf"], k3)})
    if predicate == "lm":
        p = weights.lm_prob(F.col("tf"), F.col("dl"), F.col("sum_pml"), df)

        def term(x: dict[str, Column]) -> Column:
            p = weights.lm_prob(x["tf"], x["dl"], x["sum_pml"], x["df"])
            return F.log(p) - F.log1p(-p) - F.log(weights.background(x["cf"], index.cs()))

        return Shape(lambda c: c("w") + c("comp"), {"w": term}, {"comp": F.log1p(-p)})
    if predicate == "hmm":
        a0 = params.get("a0", 0.2)
        return Shape(lambda c: c("w"), {"w": lambda x: F.log(weights.hmm_weight(x["tf"], x["dl"], x["cf"], index.cs(), a0))})
    raise ValueError(f"{predicate!r} isn't a token predicate")


def score_many(index: TokenIndex, queries, named: dict[str, tuple[str, dict]], layout: str = "posting") -> DataFrame:
    """qid, tid and one score a label, of several token predicates (label: predicate, parameters): one join, one
    aggregation, whatever their number."""
    q, terms = _prepared(index, queries)
    shapes = {f"s{i}": shape(index, predicate, **params) for i, (predicate, params) in enumerate(named.values())}
    pick = lambda part: {f"{s}_{name}": f for s, x in shapes.items() for name, f in getattr(x, part).items()}
    asked, own = pick("asked"), pick("own")
    if asked:
        terms = terms.join(terms.groupBy("qid").agg(*(f.alias(name) for name, f in asked.items())), "qid")
    out = _sums(index, terms, q, pick("shared"), layout, keep=("qlen", *asked))
    if own:
        out = out.join(index.tuple_sums(**own), "tid")
    scores = (x.score(lambda name, s=s: F.col(f"{s}_{name}")).alias(label) for (s, x), label in zip(shapes.items(), named, strict=True))
    return out.select("qid", "tid", *scores)


# ---- pruning by weight ----------------------------------------------------------------------------------------


def prune_by_weight(base_weights: DataFrame, min_weight: float | str, predicate: str = "bm25", force: bool = False) -> DataFrame:
    """(tid, token, w) without the weights below a constant, or below mean - sd / 2 ("avg-0.5sd").

    Refused for language models and HMM: dropping tokens breaks their distributions."""
    if predicate in ("lm", "hmm") and not force:
        raise ValueError(f"pruning weights of {predicate} breaks its distributions")
    if min_weight == "avg-0.5sd":
        bound = base_weights.agg((F.avg("w") - F.stddev_samp("w") * 0.5).alias("bound"))
        return base_weights.crossJoin(F.broadcast(bound)).where(F.col("w") >= F.col("bound")).drop("bound")
    return base_weights.where(F.col("w") >= float(min_weight))


def base_weights(index: TokenIndex, predicate: str = "bm25", k1: float = 1.5, b: float = 0.675) -> DataFrame:
    """tid, token, w of the tuples for the general form."""
    rows = index.with_stats()
    if predicate == "bm25":
        return rows.select("tid", "token", weights.bm25_doc_weight(weights.rs_weight(index.n(), F.col("df")), F.col("tf"), F.col("dl"), F.lit(index.meta.avgdl), k1, b).alias("w"))
    if predicate == "cosine":
        w = F.col("tf") * weights.idf(index.n(), F.col("df"))
        norms = rows.groupBy("tid").agg(F.sqrt(F.sum(w * w)).alias("norm"))
        return rows.join(norms, "tid").select("tid", "token", F.when(F.col("norm") > 0, w / F.nullif(F.col("norm"), F.lit(0.0))).otherwise(F.lit(0.0)).alias("w"))
    if predicate in ("wm", "xect"):
        return rows.select("tid", "token", (weights.rs_weight(index.n(), F.col("df")) if predicate == "wm" else F.lit(1.0)).alias("w"))
    raise ValueError(f"no stored weights for {predicate!r}")


def query_weights(index: TokenIndex, queries, predicate: str = "bm25", k3: float = 8.0) -> DataFrame:
    """qid, token, w of the queries for the general form."""
    q, terms = _prepared(index, queries)
    seen = terms.where("df is not null")
    if predicate == "bm25":
        return seen.select("qid", "token", weights.bm25_query_weight(F.col("qtf"), k3).alias("w"))
    if predicate == "cosine":
        w = F.col("qtf") * weights.idf(index.n(), F.col("df"))
        norms = seen.groupBy("qid").agg(F.sqrt(F.sum(w * w)).alias("norm"))
        return seen.join(norms, "qid").select("qid", "token", F.when(F.col("norm") > 0, w / F.nullif(F.col("norm"), F.lit(0.0))).otherwise(F.lit(0.0)).alias("w"))
    return seen.select("qid", "token", F.lit(1.0).alias("w"))
