"""Every method, variant, baseline, measure and operator as a named query, with SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import catalog_sql as q
from .functions import minhash, strsim, text, weights
from .operators import combo, edit, evaluate, exact, ranking, scoring, storage
from .operators.index import TokenIndex, TokenSpec
from .sources import tables

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_sql: dict[str, str] = {}


def add(name: str, run: Query, sql: str | None = None) -> None:
    if name in _queries:
        raise ValueError(f"two queries are named {name}")
    _queries[name] = run
    if sql:
        _sql[name] = sql


def rounded(scores: DataFrame, digits: int = 6) -> DataFrame:
    return scores.select("qid", "tid", F.round("score", digits).alias("score"))


_indexes: dict[tuple, TokenIndex] = {}


def part_index(spark: SparkSession, sf: str, kind: str = "qgram", size: int = 2, prune_rate: float = 0.0) -> TokenIndex:
    """The stored index of the part strings: preprocessing is done once for a program's queries over one input."""
    key = (spark.sparkContext.applicationId, storage.shared_dir(spark), sf, kind, size, prune_rate)
    index = _indexes.get(key)
    if index is None or not all(storage.exists(spark, f) for x in (index.rows, index.stats) for f in x.inputFiles()):
        index = part_index(spark, sf, kind, size).pruned(prune_rate) if prune_rate else TokenIndex.build(tables.part_desc(spark, sf), TokenSpec(kind, size))
        _indexes[key] = index
    return index


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """BM25 top ten of one noisy string."""
    return ranking.approx_select(part_index(spark, sf), "smal ring ECONOMY 2", "bm25", k=10)


# ---- tokens, statistics, weights ------------------------------------------------------------------------------


def _token_query(kind: str, size: int) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return part_index(spark, sf, kind, size).postings.select("tid", "token", F.col("tf").cast("long").alias("tf"))

    return run


_BAG = "SELECT tid, token, tf FROM bag"
for _name, _kind, _size in (("tok_qgram1", "qgram", 1), ("tok_qgram2", "qgram", 2), ("tok_qgram3", "qgram", 3), ("tok_qgram4", "qgram", 4), ("tok_word", "word", 2)):
    add(_name, _token_query(_kind, _size), q.scores(_BAG, kind=_kind, q=_size))


def _word_grams(spark: SparkSession, sf: str) -> DataFrame:
    rows = tables.part_desc(spark, sf).select("tid", F.explode(text.word_grams(F.col("s"), 2)).alias("x"))
    return rows.groupBy("x.word").agg(F.max(F.size("x.grams")).cast("long").alias("grams"), F.count(F.lit(1)).alias("places"))


add("tok_wordgram", _word_grams, f"SELECT word, max(length(word)) + 1 AS grams, count(*) AS places FROM (SELECT unnest(string_split(s, ' ')) AS word FROM ({q.PART_DESC})) GROUP BY word")
add("tok_edit_grams", lambda s, d: tables.names(s, d, "supplier").select("tid", F.size(text.edit_grams(F.col("s"), 3)).cast("long").alias("grams"), F.array_join(text.edit_grams(F.col("s"), 3), "|").alias("joined")),
    "SELECT tid, len(g) AS grams, array_to_string(g, '|') AS joined FROM (SELECT s_suppkey AS tid, list_transform(range(1, length(s_name) + 3), lambda i: substr('$$' || s_name || '$$', i, 3)) AS g FROM supplier)")
add("tok_normalize", lambda s, d: tables.page_title(s, d).select("tid", text.normalize(F.col("s"), "lower", True).alias("s")),
    r"SELECT page_id AS tid, trim(regexp_replace(regexp_replace(lower(regexp_extract(html, '<title>([^<]*)</title>', 1)), '[^\p{L}\p{N}\s]', '', 'g'), '\s+', ' ', 'g')) AS s FROM pages")
add("stat_terms", lambda s, d: part_index(s, d).stats.select("token", "df", "cf", F.round("sum_pml", 6).alias("sum_pml")), q.scores("SELECT token, df, cf::BIGINT AS cf, round(sum_pml, 6) AS sum_pml FROM stats"))


def _collection(spark: SparkSession, sf: str) -> DataFrame:
    m = part_index(spark, sf).meta
    return spark.createDataFrame([(m.n, m.cs, m.vocabulary, round(m.avgdl, 6), round(m.mean_idf, 6))], "n long, cs long, vocabulary long, avgdl double, mean_idf double")


add("stat_collection", _collection, q.scores("SELECT n::BIGINT AS n, cs::BIGINT AS cs, (SELECT count(*) FROM stats) AS vocabulary, round(cs / n, 6) AS avgdl, round(mean_idf, 6) AS mean_idf FROM coll"))
add("stat_idf_hist", lambda s, d: evaluate.idf_histogram(part_index(s, d, size=3), 10, 0.33).select("bin", "tokens", "postings", "dropped"),
    q.scores(f"""
, v AS (SELECT df, {q.IDF} AS idf FROM stats CROSS JOIN coll), r AS (SELECT min(idf) AS lo, max(idf) AS hi FROM v)
SELECT least(floor((idf - lo) / greatest((hi - lo) / 10, 1e-12) + 1e-9), 9)::INT AS bin, count(*) AS tokens, sum(df)::BIGINT AS postings,
       sum(CASE WHEN idf < lo + 0.33::DOUBLE * (hi - lo) - 1e-12 THEN df ELSE 0 END)::BIGINT AS dropped FROM v CROSS JOIN r GROUP BY 1""", q=3))


def _term_weight(f: Callable[[TokenIndex], F.Column]) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        i = part_index(spark, sf)
        return i.stats.select("token", F.round(f(i), 6).alias("w"))

    return run


def _posting_weight(f: Callable[[TokenIndex], F.Column]) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        i = part_index(spark, sf)
        return i.with_stats().select("tid", "token", F.round(f(i), 6).alias("w"))

    return run


_ALL = "FROM bag JOIN sizes USING (tid) JOIN stats USING (token) CROSS JOIN coll"
add("w_idf", _term_weight(lambda i: weights.idf(i.n(), F.col("df"))), q.scores(f"SELECT token, round({q.IDF}, 6) AS w FROM stats CROSS JOIN coll"))
add("w_rs", _term_weight(lambda i: weights.rs_weight(i.n(), F.col("df"))), q.scores(f"SELECT token, round({q.RS}, 6) AS w FROM stats CROSS JOIN coll"))
add("w_rs_floor", _term_weight(lambda i: weights.rs_weight(i.n(), F.col("df"), 2.0)), q.scores(f"SELECT token, round(greatest({q.RS}, 2.0::DOUBLE), 6) AS w FROM stats CROSS JOIN coll"))
add("w_tfidf", lambda s, d: scoring.base_weights(part_index(s, d), "cosine").select("tid", "token", F.round("w", 6).alias("w")),
    q.scores(f"SELECT tid, token, round(x / sqrt(sum(x * x) OVER (PARTITION BY tid)), 6) AS w FROM (SELECT tid, token, tf * {q.IDF} AS x {_ALL})"))
add("w_bm25", lambda s, d: scoring.base_weights(part_index(s, d), "bm25").select("tid", "token", F.round("w", 6).alias("w")),
    q.scores(f"SELECT tid, token, round({q.RS} * 2.5::DOUBLE * tf / (1.5::DOUBLE * (0.325::DOUBLE + 0.675::DOUBLE * dl / (cs / n)) + tf), 6) AS w {_ALL}"))
add("w_pml", _posting_weight(lambda i: weights.p_ml(F.col("tf"), F.col("dl"))), q.scores(f"SELECT tid, token, round(tf::DOUBLE / dl, 6) AS w {_ALL}"))
add("w_pavg", _term_weight(lambda i: weights.p_avg(F.col("sum_pml"), F.col("df"))), q.scores("SELECT token, round(sum_pml / df, 6) AS w FROM stats"))
add("w_lm_risk", _posting_weight(lambda i: weights.lm_risk(weights.p_avg(F.col("sum_pml"), F.col("df")), F.col("tf"), F.col("dl"))),
    q.scores(f"SELECT tid, token, round(pow(f / (1 + f), tf) / (1 + f), 6) AS w FROM (SELECT tid, token, tf, sum_pml / df * dl AS f {_ALL})"))
add("w_lm_prob", _posting_weight(lambda i: weights.lm_prob(F.col("tf"), F.col("dl"), F.col("sum_pml"), F.col("df"))), q.scores(f"SELECT tid, token, round({q.p_lm()}, 6) AS w {_ALL}"))
add("w_hmm", _posting_weight(lambda i: weights.hmm_weight(F.col("tf"), F.col("dl"), F.col("cf"), i.cs())), q.scores(f"SELECT tid, token, round(1 + 0.8::DOUBLE * (tf::DOUBLE / dl) / (0.2::DOUBLE * (cf / cs)), 6) AS w {_ALL}"))

# ---- predicates ---------------------------------------------------------------------------------------------------


def _sim(name: str, kind: str = "qgram", size: int = 2, prune: float = 0.0, **params) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return rounded(ranking.score(part_index(spark, sf, kind, size, prune_rate=prune), q.QS, name, **params))

    return run


add("sim_xect", _sim("xect"), q.simple(q.XECT))
add("sim_xect_row", _sim("xect", layout="row"), q.simple(q.XECT))
add("sim_xect_word", _sim("xect", "word"), q.simple(q.XECT, kind="word"))
add("sim_jaccard", _sim("jaccard"), q.simple(q.JACCARD))
add("sim_jaccard_q3", _sim("jaccard", size=3), q.simple(q.JACCARD, q=3))
add("sim_jaccard_word", _sim("jaccard", "word"), q.simple(q.JACCARD, kind="word"))
add("sim_wm_rs", _sim("wm"), q.simple(f"sum({q.RS})"))
add("sim_wm_idf", _sim("wm", weights="idf"), q.simple(f"sum({q.IDF})"))
add("sim_wm_floor", _sim("wm", floor=2.0), q.simple(f"sum(greatest({q.RS}, 2.0::DOUBLE))"))
add("sim_wj_rs", _sim("wj"), q.sql_wj("rs"))
add("sim_wj_idf", _sim("wj", weights="idf"), q.sql_wj("idf"))
add("sim_wj_row", _sim("wj", layout="row"), q.sql_wj("rs"))
add("sim_cosine", _sim("cosine"), q.sql_cosine())
add("sim_cosine_q3", _sim("cosine", size=3), q.sql_cosine(q=3))
add("sim_cosine_word", _sim("cosine", "word"), q.sql_cosine(kind="word"))
add("sim_bm25", _sim("bm25"), q.simple(q.sql_bm25()))
add("sim_bm25_row", _sim("bm25", layout="row"), q.simple(q.sql_bm25()))
add("sim_bm25_q3", _sim("bm25", size=3), q.simple(q.sql_bm25(), q=3))
add("sim_bm25_params", _sim("bm25", k1=1.2, k3=7.0, b=0.75), q.simple(q.sql_bm25(1.2, 7.0, 0.75)))
add("sim_bm25_full", lambda s, d: rounded(scoring.score_bm25(TokenIndex.build(tables.part_full(s, d)), q.QS)), q.simple(q.sql_bm25(), base=q.PART_FULL))
add("sim_weighted_sum", lambda s, d: rounded(scoring.score_weighted_sum(scoring.base_weights(i := part_index(s, d)), scoring.query_weights(i, q.QS))), q.simple(q.sql_bm25()))
add("sim_lm", _sim("lm", log=True), q.sql_lm())
add("sim_lm_row", _sim("lm", log=True, layout="row"), q.sql_lm())
add("sim_lm_full", _sim("lm", form="full", log=True), q.sql_lm(True))
add("sim_hmm", _sim("hmm", log=True), q.simple(f"sum({q.hmm_term()})"))
add("sim_hmm_row", _sim("hmm", log=True, layout="row"), q.simple(f"sum({q.hmm_term()})"))
add("sim_hmm_a0", _sim("hmm", log=True, a0=0.5), q.simple(f"sum({q.hmm_term(0.5)})"))
add("sim_hmm_full", _sim("hmm", form="full", log=True), q.sql_hmm_full())
add("sim_hmm_bag", _sim("hmm", query_semantics="bag", log=True), q.simple(f"sum(qtf * {q.hmm_term()})"))


def _exact(name: str, **params) -> Query:
    return lambda s, d: rounded(exact.score_all(part_index(s, d), q.QS, name, **params))


def _with_zeros(sql: str, rest: str = "0.0::DOUBLE") -> str:
    return f"SELECT y.qid, b.tid, coalesce(f.score, {rest}) AS score FROM ({q.PART_DESC}) b CROSS JOIN ({q.values()}) y LEFT JOIN ({sql}) f ON f.qid = y.qid AND f.tid = b.tid"


add("exact_xect", _exact("xect"), _with_zeros(q.simple(q.XECT)))
add("exact_jaccard", _exact("jaccard"), _with_zeros(q.simple(q.JACCARD)))
add("exact_wm", _exact("wm"), _with_zeros(q.simple(f"sum({q.RS})")))
add("exact_wj", _exact("wj"), _with_zeros(q.sql_wj("rs")))
add("exact_cosine", _exact("cosine"), _with_zeros(q.sql_cosine()))
add("exact_bm25", _exact("bm25"), _with_zeros(q.simple(q.sql_bm25())))
add("exact_hmm", _exact("hmm", log=True), _with_zeros(q.simple(f"sum({q.hmm_term()})")))
add("exact_lm", _exact("lm", log=True), f"SELECT x.qid, x.tid, round(coalesce(f.score, o.comp), 6) AS score FROM (SELECT y.qid, b.tid FROM ({q.PART_DESC}) b CROSS JOIN ({q.values()}) y) x LEFT JOIN ({q.sql_lm()}) f ON f.qid = x.qid AND f.tid = x.tid JOIN ({q.scores(f'SELECT tid, sum(ln(1 - p)) AS comp FROM (SELECT tid, {q.p_lm()} AS p FROM bag JOIN sizes USING (tid) JOIN stats USING (token)) GROUP BY tid')}) o ON o.tid = x.tid")
add("exact_ges_bound", lambda s, d: rounded(exact.score_all(part_index(s, d, "word"), q.QS, "ges_bound")), _with_zeros(q.ges_bound(q.gram_sims()), "0.5::DOUBLE"))
add("exact_soft", lambda s, d: rounded(exact.score_all(part_index(s, d, "word"), q.QS, "soft_tfidf")), _with_zeros(q.soft(q.JW_SIMS, 0.8)))


def _many(spark: SparkSession, sf: str) -> DataFrame:
    """Eight predicates in one pass."""
    named = {"xect": ("xect", {}), "jaccard": ("jaccard", {}), "wm": ("wm", {}), "wj": ("wj", {}), "cosine": ("cosine", {}), "bm25": ("bm25", {}), "lm": ("lm", {}), "hmm": ("hmm", {})}
    out = scoring.score_many(part_index(spark, sf), q.QS, named)
    return out.select("qid", "tid", *(F.round(c, 6).alias(c) for c in named))


_ONE = {"xect": q.simple(q.XECT), "jaccard": q.simple(q.JACCARD), "wm": q.simple(f"sum({q.RS})"), "wj": q.sql_wj("rs"), "cosine": q.sql_cosine(), "bm25": q.simple(q.sql_bm25()), "lm": q.sql_lm(), "hmm": q.simple(f"sum({q.hmm_term()})")}
add("sim_many", _many, "SELECT xect.qid, xect.tid, " + ", ".join(f"{c}.score AS {c}" for c in _ONE) + " FROM (" + q.simple(q.XECT) + ") xect " + " ".join(f"JOIN ({s}) {c} ON {c}.qid = xect.qid AND {c}.tid = xect.tid" for c, s in _ONE.items() if c != "xect"))


def _edit(theta: float | None = None, **params) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        rel = tables.part_desc(spark, sf)
        return rounded(edit.score_edit(rel, q.QS, **params) if theta is None else edit.edit_select(rel, q.QS, theta, **params))

    return run


add("sim_edit", _edit(), q.edit())
add("sim_edit_costs", _edit(costs={"insert": 1.0, "delete": 1.0, "substitute": 1.5, "swap": 1.0}), q.edit_costs(1.0, 1.0, 1.5, 1.0))
add("sel_edit_07", _edit(0.7), q.edit(0.7))
add("sel_edit_07_bag", _edit(0.7, positional=False), q.edit(0.7))
add("sel_edit_05", _edit(0.5), q.edit(0.5))
add("sel_edit_04_vacuous", _edit(0.4), q.edit(0.4))
add("sim_ges", _sim("ges", "word"), q.ges())
add("sim_ges_udf", _sim("ges", "word", native=False), q.ges())
add("sim_ges_jaccard", _sim("ges_bound", "word"), q.ges_bound(q.gram_sims()))
add("sim_ges_apx_h5", _sim("ges_bound", "word", sim="minhash"), q.ges_bound(q.minhash_sims(minhash.coefficients(5))))
for _filter, _sims in (("jaccard", q.gram_sims()), ("minhash", q.minhash_sims(minhash.coefficients(5))), ("none", None)):
    for _name, _theta in (("08", 0.8), ("06", 0.6)):
        add(f"sel_ges_{_name}_{_filter}", lambda s, d, f=_filter, t=_theta: rounded(combo.ges_select(part_index(s, d, "word"), q.QS, t, f)), q.ges(_theta, _sims))
add("sim_soft_jw", _sim("soft_tfidf", "word"), q.soft(q.JW_SIMS, 0.8))
add("sim_soft_edit", _sim("soft_tfidf", "word", word_sim="edit", theta=0.6), q.soft(q.EDIT_SIMS, 0.6))
add("sim_soft_jaccard", _sim("soft_tfidf", "word", word_sim="jaccard", theta=0.4), q.soft(q.gram_sims(), 0.4))
add("sim_soft_intersect", _sim("soft_tfidf", "word", word_sim="intersect", theta=2.0), q.soft(q.gram_sims("intersect"), 2.0))


def _name_pairs(spark: SparkSession, sf: str) -> DataFrame:
    a = tables.load(spark, sf, "part").select(F.col("p_name").alias("a")).distinct()
    b = tables.load(spark, sf, "part").select(F.col("p_type").alias("b")).distinct()
    names = a.crossJoin(a.select(F.col("a").alias("b"))).unionByName(a.crossJoin(b))
    return names.select("a", "b", F.round(strsim.jaro_winkler(F.col("a"), F.col("b")), 6).alias("jw"), F.round(strsim.jaro(F.col("a"), F.col("b")), 6).alias("jaro"))


add("word_jw", _name_pairs, """
WITH a AS (SELECT DISTINCT p_name AS a FROM part), p AS (SELECT x.a AS a, y.a AS b FROM a x CROSS JOIN a y UNION ALL SELECT a, b FROM a CROSS JOIN (SELECT DISTINCT p_type AS b FROM part))
SELECT a, b, round(jaro_winkler_similarity(a, b), 6) AS jw, round(jaro_similarity(a, b), 6) AS jaro FROM p""")


def _signatures(spark: SparkSession, sf: str) -> DataFrame:
    w = tables.load(spark, sf, "part").select(F.col("p_name").alias("word")).distinct()
    return w.select("word", F.posexplode(minhash.minhash_signature(text.qgrams(F.col("word"), 2), 5)).alias("fid", "value"))


add("word_minhash", _signatures, f"""
WITH w AS (SELECT DISTINCT p_name AS word FROM part), g AS ({q.word_grams('SELECT word FROM w')}), h AS (SELECT word, ('0x' || substr(md5(token), 1, 8))::BIGINT % 2147483647 AS h FROM g),
s AS (SELECT word, [{', '.join(f'min((h * {a} + {b}) % 2147483647)' for a, b in minhash.coefficients(5))}] AS sig FROM h GROUP BY word)
SELECT word, unnest(range(5))::INT AS fid, unnest(sig)::BIGINT AS value FROM s""")

# ---- selections, joins, pruning -----------------------------------------------------------------------------------

_BM25 = f"SELECT qid, tid, {q.sql_bm25()} AS score FROM met GROUP BY qid, tid"
add("topk_bm25", lambda s, d: rounded(ranking.approx_select(part_index(s, d), q.QS, "bm25", k=10)), q.scores(f"SELECT qid, tid, round(score, 6) AS score FROM ({q.ranked(_BM25)}) WHERE rank <= 10"))
add("topk_single", lambda s, d: rounded(flagship(s, d)), q.scores(f"SELECT qid, tid, round(score, 6) AS score FROM ({q.ranked(_BM25)}) WHERE rank <= 10 AND qid = 1"))
add("sel_bm25", lambda s, d: rounded(ranking.approx_select(part_index(s, d), q.QS, "bm25", threshold=12.0)), q.scores(f"SELECT qid, tid, round(score, 6) AS score FROM ({_BM25}) WHERE round(score, 9) >= 12"))
add("sel_jaccard", lambda s, d: rounded(ranking.approx_select(part_index(s, d), q.QS, "jaccard", threshold=0.5)), q.scores(f"SELECT * FROM (SELECT qid, tid, round({q.JACCARD}, 6) AS score FROM met GROUP BY qid, tid) WHERE score >= 0.5"))
add("rank_all_hmm", lambda s, d: ranking.rank_all(ranking.score(part_index(s, d), q.QS, "hmm", log=True)).select("qid", "tid", "rank"),
    q.scores(f"SELECT qid, tid, rank FROM ({q.ranked(f'SELECT qid, tid, sum({q.hmm_term()}) AS score FROM met GROUP BY qid, tid')})"))


def _join_jaccard(spark: SparkSession, sf: str) -> DataFrame:
    left = TokenIndex.build(tables.names(spark, sf, "supplier"))
    right = tables.names(spark, sf, "customer").select(F.col("tid").alias("qid"), "s")
    return rounded(ranking.approx_join(left, right, "jaccard", 0.3))


_NAMES = ("SELECT s_suppkey AS tid, s_name AS s FROM supplier", "SELECT c_custkey AS qid, c_name AS s FROM customer")
add("join_jaccard", _join_jaccard, q.scores(f"SELECT * FROM (SELECT qid, tid, round({q.JACCARD}, 6) AS score FROM met GROUP BY qid, tid) WHERE score >= 0.3", base=_NAMES[0], queries=_NAMES[1]))
add("join_bm25_top3", lambda s, d: rounded(ranking.approx_join(TokenIndex.build(tables.names(s, d, "supplier")), tables.names(s, d, "customer").select(F.col("tid").alias("qid"), "s"), "bm25", k=3)),
    q.scores(f"SELECT qid, tid, round(score, 6) AS score FROM ({q.ranked(_BM25)}) WHERE rank <= 3", base=_NAMES[0], queries=_NAMES[1]))
add("exact_match", lambda s, d: ranking.exact_match(tables.part_desc(s, d), tables.part_desc(s, d).select(F.col("tid").alias("qid"), "s")),
    f"SELECT a.tid AS qid, b.tid AS tid FROM ({q.PART_DESC}) a JOIN ({q.PART_DESC}) b ON a.s = b.s")
add("selfjoin_dedup", lambda s, d: ranking.dedup(TokenIndex.build(tables.doc_text(s, d), TokenSpec("word"), strings=False), "jaccard", 0.7), r"""
WITH RECURSIVE w AS (SELECT doc_id AS tid, list_distinct(string_split(trim(regexp_replace(text, '\s+', ' ', 'g')), ' ')) AS t FROM documents WHERE trim(regexp_replace(text, '\s+', ' ', 'g')) <> ''),
e AS (SELECT tid, unnest(t) AS token, len(t) AS n FROM w),
l AS (SELECT a.tid AS a, b.tid AS b FROM e a JOIN e b ON a.token = b.token AND a.tid <> b.tid GROUP BY a.tid, b.tid, a.n, b.n HAVING round(count(*)::DOUBLE / (a.n + b.n - count(*)), 9) >= 0.7),
r(tid, x) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.tid, l.b FROM r JOIN l ON l.a = r.x)
SELECT tid, min(x) AS cluster FROM r GROUP BY tid""")


def _prune(name: str, rate: float, **params) -> Query:
    return _sim(name, prune=rate, **params)


add("prune_02_bm25", _prune("bm25", 0.2), q.simple(q.sql_bm25(), prune=0.2))
add("prune_033_xect", _prune("xect", 0.33), q.simple(q.XECT, prune=0.33))
add("prune_05_jaccard", _prune("jaccard", 0.5), q.simple(q.JACCARD, prune=0.5))
add("prune_02_hmm", _prune("hmm", 0.2, log=True), q.simple(f"sum({q.hmm_term()})", prune=0.2))


def _weight_pruned(predicate: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        i = part_index(spark, sf)
        kept = scoring.prune_by_weight(scoring.base_weights(i, predicate), "avg-0.5sd", predicate)
        return rounded(scoring.score_weighted_sum(kept, scoring.query_weights(i, q.QS, predicate)))

    return run


add("prune_weight_bm25", _weight_pruned("bm25"), q.scores(f"""
, dw AS (SELECT tid, token, {q.RS} * 2.5::DOUBLE * tf / (1.5::DOUBLE * (0.325::DOUBLE + 0.675::DOUBLE * dl / (cs / n)) + tf) AS w {_ALL})
SELECT qid, tid, round(sum(w * 9.0::DOUBLE * tf / (8 + tf)), 6) AS score FROM dw JOIN qbag USING (token) WHERE w >= (SELECT avg(w) - 0.5::DOUBLE * stddev_samp(w) FROM dw) GROUP BY qid, tid"""))
add("prune_weight_cosine", _weight_pruned("cosine"), q.scores(f"""
, d1 AS (SELECT tid, token, tf * {q.IDF} AS w {_ALL}), dw AS (SELECT tid, token, w / sqrt(sum(w * w) OVER (PARTITION BY tid)) AS w FROM d1),
q1 AS (SELECT qid, token, tf * {q.IDF} AS w FROM qbag JOIN stats USING (token) CROSS JOIN coll), qw AS (SELECT qid, token, w / sqrt(sum(w * w) OVER (PARTITION BY qid)) AS wq FROM q1)
SELECT qid, tid, round(sum(w * wq), 6) AS score FROM dw JOIN qw USING (token) WHERE w >= (SELECT avg(w) - 0.5::DOUBLE * stddev_samp(w) FROM dw) GROUP BY qid, tid"""))


def _appended(spark: SparkSession, sf: str) -> DataFrame:
    rel = tables.part_desc(spark, sf)
    i = TokenIndex.build(rel.where("tid % 3 <> 0")).append(rel.where("tid % 3 = 0"))
    return rounded(scoring.score_bm25(i, q.QS))


add("index_append", _appended, q.simple(q.sql_bm25()))

# ---- evaluation -----------------------------------------------------------------------------------------------------


def _ranked_sample(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame, evaluate.Classes]:
    """Every string against all, to the rank q.CUT; relevant are those of one name and type. Equal strings are ranked once:
    (head, qid), the ranking of the heads, the classes."""
    part = tables.load(spark, sf, "part").select(F.col("p_partkey").cast("long").alias("tid"), F.concat("p_name", F.lit("\0"), "p_type").alias("class"))
    asked = tables.part_desc(spark, sf).join(part, "tid").select(F.col("tid").alias("qid"), "s", "class")
    members, ranked = ranking.top_k_copies(part_index(spark, sf), asked, q.CUT, "bm25")
    return members, ranked, evaluate.Classes(part.withColumnRenamed("tid", "qid"), part)


def _measure(f: Callable[[DataFrame, evaluate.Classes, DataFrame], DataFrame]) -> Query:
    """f of the heads' ranking, the truth and the heads, given to every query."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        members, ranked, truth = _ranked_sample(spark, sf)
        out = f(ranked, truth, members.where("qid = head").select("qid"))
        return out.withColumnRenamed("qid", "head").join(members, "head").select("qid", *(c for c in out.columns if c != "qid"))

    return run


def _mean_measure(f: Callable[..., DataFrame], name: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        members, ranked, truth = _ranked_sample(spark, sf)
        copies = members.groupBy(F.col("head").alias("qid")).agg(F.count(F.lit(1)).alias("copies"))
        return f(ranked, truth, copies.select("qid"), copies).select(F.round(name, 6).alias(name))

    return run


def _ap_by_udf(ranked: DataFrame, truth: evaluate.Classes, asked: DataFrame) -> DataFrame:
    """The function's mean is over the relevant tuples returned; those beyond the cut count as well."""
    found = evaluate.judged(ranked, truth).join(evaluate.relevant(truth), "qid")
    per = found.groupBy("qid", "relevant").agg(evaluate.average_precision_udf("rel", "rank").alias("ap"))
    hits = found.groupBy("qid").agg(F.sum("rel").alias("hits"))
    return per.join(hits, "qid").select("qid", F.round(F.col("ap") * F.col("hits") / F.col("relevant"), 6).alias("ap"))


add("eval_pr", _measure(lambda r, t, a: evaluate.pr_curve(r, t).select("qid", "tid", "rank", "rel", F.round("precision", 6).alias("precision"), F.round("recall", 6).alias("recall"))),
    q.evaluated("SELECT qid, tid, rank, rel, round(precision, 6) AS precision, round(recall, 6) AS recall FROM pr"))
add("eval_ap", _measure(lambda r, t, a: evaluate.average_precision(r, t, a).select("qid", F.round("ap", 6).alias("ap"))), q.evaluated("SELECT qid, round(ap, 6) AS ap FROM ap"))
add("eval_map", _mean_measure(evaluate.mean_average_precision, "map"), q.evaluated("SELECT round(avg(ap), 6) AS map FROM ap"))
add("eval_maxf1", _mean_measure(evaluate.mean_max_f1, "mean_max_f1"), q.evaluated("SELECT round(avg(f1), 6) AS mean_max_f1 FROM ap"))
add("eval_ap_udf", _measure(_ap_by_udf), q.evaluated("SELECT qid, round(ap, 6) AS ap FROM ap"))
add("eval_ranks_of", _measure(lambda r, t, a: evaluate.ranks_of(r, [0, 1, 2, 3, 4, 5])), q.evaluated("SELECT qid, tid, rank FROM rk WHERE tid IN (0, 1, 2, 3, 4, 5)"))


def _filter_report(spark: SparkSession, sf: str) -> DataFrame:
    rel = tables.part_desc(spark, sf)
    found = evaluate.filter_report(edit.edit_candidates(rel, q.QS, 0.7, positional=False), edit.score_edit(rel, q.QS).where("score >= 0.7"), rel.count() * len(q.QS))
    return spark.createDataFrame([(int(found["candidates"]), round(float(found["share"]), 9), int(found["missed"]))], "candidates long, share double, missed long")


add("eval_filter_edit", _filter_report, q.filter_edit(0.7))
_DOCS = "SELECT doc_id AS tid, text AS s FROM documents WHERE text IS NOT NULL"


def _retrieve(spark: SparkSession, sf: str) -> DataFrame:
    index = TokenIndex.build(tables.doc_text(spark, sf).where("s is not null"), TokenSpec("word"))
    return rounded(ranking.top_k(scoring.score_bm25(index, tables.passages(spark, sf)), 10), 4)


add("retrieve_passages", _retrieve, q.scores(f"SELECT qid, tid, round(score, 4) AS score FROM ({q.ranked(_BM25)}) WHERE rank <= 10", base=_DOCS, queries="SELECT item_id AS qid, text AS s FROM benchmark", kind="word"))


def queries() -> dict[str, Query]:
    from . import catalog_more

    return _queries | catalog_more.queries()


def oracle_sql() -> dict[str, str]:
    from . import catalog_more

    return _sql | catalog_more.oracle_sql()
