"""Selections, rankings, joins and duplicate clusters over any predicate."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text, weights
from . import blocks, combo, edit, scoring
from .index import MOST_BROADCAST, Queries, TokenIndex, broadcast_up_to
from .storage import shared_dir, stored

PREDICATES = {
    "xect": scoring.score_xect, "jaccard": scoring.score_jaccard, "wm": scoring.score_wm, "wj": scoring.score_wj,
    "cosine": scoring.score_cosine, "bm25": scoring.score_bm25, "lm": scoring.score_lm, "hmm": scoring.score_hmm,
    "ges": combo.score_ges, "ges_bound": combo.score_ges_bound, "soft_tfidf": combo.score_soft_tfidf,
    "edit": lambda index, queries, **p: edit.score_edit(index.rows.select("tid", "s"), queries, **p),
}

#: Digits that order scores: floating-point noise of another order of addition must not decide a rank.
DIGITS = 9
#: Ids of equal rows that a row carries.
COPIES = 1024
#: Tokens of their prefixes that two long sets must share before they are compared.
SHARED = 12


def score(index: TokenIndex, queries, predicate: str, **params) -> DataFrame:
    if predicate not in PREDICATES:
        raise ValueError(f"unknown predicate {predicate!r}; one of {', '.join(PREDICATES)}")
    return PREDICATES[predicate](index, queries, **params)


def rank_all(scores: DataFrame, digits: int = DIGITS) -> DataFrame:
    """scores with their rank in the query: by falling score, then tid."""
    order = Window.partitionBy("qid").orderBy(F.round("score", digits).desc(), "tid")
    return scores.withColumn("rank", F.row_number().over(order))


def top_k(scores: DataFrame, k: int, single: bool = False) -> DataFrame:
    """The k best of each query. With single=True the scores are of one query: k rows a task, no window."""
    if single:
        return scores.orderBy(F.round("score", DIGITS).desc(), "tid").limit(k)
    return rank_all(scores).where(F.col("rank") <= k)


def approx_select(index: TokenIndex, queries, predicate: str = "bm25", threshold: float | None = None, k: int | None = None, **params) -> DataFrame:
    """qid, tid, score of the tuples with score >= threshold, or the k best of each query, or all scored ones."""
    q = Queries.of(index.rows.sparkSession, queries)
    if predicate == "edit" and threshold is not None:
        out = edit.edit_select(index.rows.select("tid", "s"), q, threshold, **params)
    elif predicate == "ges" and threshold is not None:
        out = combo.ges_select(index, q, threshold, **params)
    else:
        out = score(index, q, predicate, **params)
        if threshold is not None:
            out = out.where(F.round("score", DIGITS) >= threshold)
    return out if k is None else top_k(out, k, single=q.rows == 1).select("qid", "tid", "score")


def of_copies(index: TokenIndex, asked: Queries, scored: Callable[[TokenIndex, Queries], DataFrame]) -> DataFrame:
    """scored (qid, tid, score) of all rows on either side, run once for each different string. Statistics are of all
    tuples; tuples without a string are left as they are."""
    own = lambda df, key, by: df.select(key, by, F.min(key).over(Window.partitionBy(by)).alias("head"))
    given = stored(own(index.rows, "tid", "s"))
    members = stored(own(asked.frame, "qid", "s"))
    rows = stored(index.rows.join(given.where("tid = head").select("tid"), "tid", "left_semi"))
    slim = TokenIndex(index.spec, rows, index.stats, index.meta, index.dropped)
    heads = members.where("qid = head").select("qid", "s")
    few = scored(slim, Queries(stored(heads), asked.rows))
    few = few.join(broadcast_up_to(given.select(F.col("head").alias("first"), F.col("tid").alias("t")), index.meta.n), F.col("tid") == F.col("first"))
    few = few.select("qid", F.col("t").alias("tid"), "score")
    copies = members.select("head", F.col("qid").alias("q"))
    return few.join(broadcast_up_to(copies, asked.rows), F.col("qid") == F.col("head")).select(F.col("q").alias("qid"), "tid", "score")


def top_k_copies(index: TokenIndex, asked: DataFrame, k: int, predicate: str = "bm25", **params) -> tuple[DataFrame, DataFrame]:
    """The k best tuples of every row of asked (qid, s, further columns), each different string scored once on either side.

    Returns (head, qid): rows of asked and the least qid with the same values, and the ranking of the heads (qid, tid,
    score, rank). Of a string's tuples the first k can be among the k best, and of the strings the k best by score and
    first tuple, so that the ranks are those of all rows. Statistics are of all tuples."""
    by = [c for c in asked.columns if c != "qid"]
    members = stored(asked.withColumn("head", F.min("qid").over(Window.partitionBy(*by))))
    heads = members.where("qid = head").select("qid", "s")
    own = Window.partitionBy("s").orderBy("tid")
    first = index.rows.where("s is not null").select("tid", "s").withColumn("place", F.row_number().over(own)).where(F.col("place") <= k)
    first = stored(first.withColumn("first", F.min("tid").over(Window.partitionBy("s"))).select("first", "tid"))
    rows = stored(index.rows.join(first.where("tid = first").select("tid"), "tid", "left_semi"))
    slim = TokenIndex(index.spec, rows, index.stats, index.meta, index.dropped)
    tokens, n = rows.agg(F.coalesce(F.sum("len"), F.lit(0))).first()[0], heads.count()
    if predicate == "bm25" and params.keys() <= {"k1", "k3", "b"}:
        few = bm25_blocks(slim, heads, k, tokens, n, **params)
    else:
        if predicate in scoring.TOKEN_PREDICATES and tokens <= MOST_BROADCAST:
            params = {"layout": "query"} | params
        few = top_k(score(slim, Queries(heads, n if n <= MOST_BROADCAST else None), predicate, **params), k)
    every = few.select("qid", F.col("tid").alias("first"), "score").join(first, "first").select("qid", "tid", "score")
    return members.select("head", "qid"), top_k(every, k)


def bm25_blocks(index: TokenIndex, asked: DataFrame, k: int, tokens: int, queries: int, k1: float = 1.5, k3: float = 8.0, b: float = 0.675) -> DataFrame:
    """qid, tid, score of the rows of asked (qid, s): the k best of each block of tuples, so that the k best are among them."""
    w = scoring.base_weights(index, "bm25", k1, b).groupBy("tid").agg(F.collect_list(F.struct("token", "w")).alias("x"))
    tuples = stored(w.select(F.col("tid").alias("id"), "x.token", "x.w").withColumnRenamed("token", "tokens"))
    bag = text.token_bag(index.spec.tokens(F.col("s")))
    mine = asked.where("s is not null").select(F.col("qid").alias("id"), bag.alias("bag"))
    weight = F.transform("bag", lambda x: weights.bm25_query_weight(x["tf"], k3))
    return blocks.top_k_sums(tuples, mine.select("id", F.transform("bag", lambda x: x["token"]).alias("tokens"), weight.alias("w")), k, tokens, queries)


def approx_join(index: TokenIndex, right: DataFrame, predicate: str = "jaccard", threshold: float | None = None, k: int | None = None, **params) -> DataFrame:
    """The selection for each row (qid, s) of right. Its size is unknown, so nothing of it is broadcast. A join
    without a threshold or k is close to the cross product and is refused."""
    if threshold is None and k is None:
        raise ValueError("an approximate join needs a threshold or k")
    if predicate == "jaccard" and threshold is not None and threshold > 0:
        out = jaccard_join_copies(index, right, threshold)
        return out if k is None else top_k(out, k).select("qid", "tid", "score")
    if threshold is None and predicate in scoring.TOKEN_PREDICATES:
        members, best = top_k_copies(index, right.select(F.col("qid").cast("long").alias("qid"), "s"), k, predicate, **params)
        return best.withColumnRenamed("qid", "head").join(members, "head").select("qid", "tid", "score")
    return approx_select(index, Queries(right), predicate, threshold, k, **params)


def jaccard_join(index: TokenIndex, right: DataFrame, threshold: float) -> DataFrame:
    """Jaccard join: qid, tid, score of the pairs of at least the threshold, and of their copies where rows have a column
    `copies` (ids of the rows that are equal, with their own). Pairs are counted block by block, none are shuffled."""
    token = F.transform("bag", lambda x: x["token"])
    asked = right.select(F.col("qid").cast("long").alias("qid"), *(c for c in right.columns if c != "qid")).where("s is not null")
    asked = asked.withColumn("bag", text.token_bag(index.spec.tokens(F.col("s"))))

    def shaped(rows: DataFrame, key: str) -> DataFrame:
        copies = F.col("copies") if "copies" in rows.columns else F.array(key)
        return rows.where(F.size("bag") > 0).select(F.col(key).alias("id"), F.size("bag").alias("size"), token.alias("tokens"), copies.alias("copies"))

    tokens, n = index.rows.agg(F.coalesce(F.sum("len"), F.lit(0))).first()[0], right.count()
    pairs = blocks.jaccard_pairs(shaped(index.rows, "tid"), shaped(asked, "qid"), threshold, tokens, n)
    return pairs.where(F.round("score", DIGITS) >= threshold)


def jaccard_join_copies(index: TokenIndex, right: DataFrame, threshold: float) -> DataFrame:
    """jaccard_join of the different bags and strings, with their copies. No row has more than COPIES of these, so that
    none grows with the number of equal rows."""

    def grouped(df: DataFrame, key: str, by: str, *kept: str) -> DataFrame:
        place = F.row_number().over(Window.partitionBy(by).orderBy(key))
        chunks = df.withColumn("chunk", F.floor((place - 1) / COPIES)).groupBy(by, "chunk")
        return stored(chunks.agg(F.min(key).alias(key), F.array_sort(F.collect_list(key)).alias("copies"), *(F.min(c).alias(c) for c in kept)).drop("chunk"))

    asked = grouped(right.select(F.col("qid").cast("long").alias("qid"), "s").where("s is not null"), "qid", "s")
    rows = grouped(index.rows.where("len > 0"), "tid", "bag", "s", "len", "dl")
    return jaccard_join(TokenIndex(index.spec, rows, index.stats, index.meta, index.dropped), asked, threshold)


def exact_match(left: DataFrame, right: DataFrame) -> DataFrame:
    """qid, tid of equal strings: the lower baseline."""
    return right.select("qid", "s").join(left.select("tid", "s"), "s").select("qid", "tid")


def connected(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """tid, cluster (least tid reachable) of nodes (tid) under pairs (a, b): least labels of neighbours, with the
    label's own label looked up in each round, until nothing changes. Rounds are checkpointed to the shared folder."""
    spark = pairs.sparkSession
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(shared_dir(spark))
    edges = pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct().checkpoint()
    labels = edges.select(F.col("a").alias("tid")).distinct().withColumn("c", F.col("tid")).checkpoint()
    while True:
        near = edges.join(labels, F.col("b") == F.col("tid")).groupBy("a").agg(F.min("c").alias("m"))
        new = labels.join(near, F.col("tid") == F.col("a")).select("tid", F.least("c", "m").alias("c"))
        jump = labels.select(F.col("tid").alias("t2"), F.col("c").alias("c2"))
        new = new.join(jump, F.col("c") == F.col("t2")).select("tid", F.least("c", "c2").alias("c")).checkpoint()
        moved = new.alias("n").join(labels.alias("l"), "tid").where("n.c <> l.c").limit(1).count()
        labels = new
        if not moved:
            break
    return nodes.select("tid").join(labels, "tid", "left").select("tid", F.coalesce("c", "tid").alias("cluster"))


def set_links(index: TokenIndex, threshold: float) -> tuple[DataFrame, DataFrame]:
    """tid, head (least tid with the same tokens) of the tuples with tokens, and the links (a, b) between different heads
    whose sets reach the threshold. Sets are dealt out by tid once, and their tokens ordered in place by the broadcast
    counts of the most frequent tokens; the others are taken as rarer than these.

    Sets of n and m tokens share at least o = ceil(t / (1 + t) * (n + m)) of them. Of one order of tokens, their first
    n - o + k and m - o + k then share k, so that words that two long texts share by chance make no candidates."""
    t = threshold - 1e-9
    # sets travel as one string; of the kinds of tokens only "edit" may hold a line end
    coded = F.hex if index.spec.kind == "edit" else lambda x: x
    joined = F.array_join(F.transform("bag", lambda x: coded(x["token"])), "\n")
    rows = index.rows.where("len > 0").select("tid", joined.alias("t"))
    keyed = rows.select("tid", F.sha2("t", 256).alias("key"))
    heads = stored(keyed.join(keyed.groupBy("key").agg(F.min("tid").alias("head")), "key").select("tid", "head"))
    sets = rows.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), "tid")
    common = index.stats.select(coded(F.col("token")).alias("token"), "df")
    if index.meta.vocabulary > MOST_BROADCAST:
        common = common.orderBy(F.desc("df"), "token").limit(MOST_BROADCAST)
    each = sets.join(heads.where("tid = head").select("tid"), "tid", "left_semi").withColumn("t", F.split("t", "\n")).select("tid", F.size("t").alias("len"), F.explode("t").alias("token"))
    each = each.join(F.broadcast(common), "token", "left").withColumn("h", F.xxhash64("token"))
    place = F.row_number().over(Window.partitionBy("tid").orderBy(F.coalesce("df", F.lit(0)), "h", "token"))
    reach = F.col("len") - F.ceil(F.col("len") * t) + SHARED
    # a token of one tuple meets nothing
    prefixes = each.withColumn("place", place).where((F.col("place") <= reach) & (F.coalesce("df", F.lit(2)) > 1))
    met = prefixes.groupBy("h").agg(F.sort_array(F.collect_list(F.struct("tid", "len", "place"))).alias("all")).where(F.size("all") > 1)
    met = met.select("all", F.posexplode("all").alias("i", "a")).select("a", F.explode(F.slice("all", F.col("i") + 2, F.size("all"))).alias("b"))
    met = met.withColumn("o", F.ceil((F.col("a.len") + F.col("b.len")) * (t / (1 + t)))).withColumn("k", F.least(F.lit(SHARED), "o"))
    near = " AND ".join(f"{x}.place <= {x}.len - o + k" for x in "ab") + " AND o <= least(a.len, b.len) AND a.tid <> b.tid"
    pairs = met.where(near).groupBy(F.col("a.tid").alias("a"), F.col("b.tid").alias("b"), "k").agg(F.count(F.lit(1)).alias("n")).where("n >= k").select("a", "b")
    both = pairs.join(sets.select(F.col("tid").alias("a"), F.col("t").alias("x")), "a").join(sets.select(F.col("tid").alias("b"), F.col("t").alias("y")), "b")
    both = both.select("a", "b", F.split("x", "\n").alias("x"), F.split("y", "\n").alias("y"))
    n = F.size(F.array_intersect("x", "y")).cast("double")
    return heads, stored(both.where(F.round(n / (F.size("x") + F.size("y") - n), DIGITS) >= threshold).select("a", "b"))


def dedup(index: TokenIndex, predicate: str = "jaccard", threshold: float = 0.8, **params) -> DataFrame:
    """tid, cluster: connected components of the self-join. Copies are one node: each different string (by Jaccard, each
    different set of tokens) is matched once. Tuples without tokens share nothing and stay apart by Jaccard."""
    if predicate == "jaccard" and threshold > 0:
        heads, links = set_links(index, threshold)
        copies = heads.select(F.col("tid").alias("a"), F.col("head").alias("b")).where("a <> b")
        return connected(links.unionByName(copies), index.rows)
    rows = index.rows.select("tid", "s").where("s is not null")
    heads = rows.groupBy("s").agg(F.min("tid").alias("tid"))
    slim = TokenIndex(index.spec, index.rows.join(heads.select("tid"), "tid", "left_semi"), index.stats, index.meta, index.dropped)
    pairs = approx_join(slim, heads.select(F.col("tid").alias("qid"), "s"), predicate, threshold, **params).where("qid <> tid")
    pairs = pairs.select(F.least("qid", "tid").alias("a"), F.greatest("qid", "tid").alias("b")).distinct()
    copies = rows.join(heads.withColumnRenamed("tid", "b"), "s").select(F.col("tid").alias("a"), "b").where("a <> b")
    return connected(pairs.unionByName(copies), index.rows)
