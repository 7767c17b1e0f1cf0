"""The accuracy and cost workloads, over stand-in names and titles with generated errors.

`QUERIES` registers them with the published 500 queries a set (100 for times), for every predicate; `asked` is a parameter.
`python -m approxmatch.experiments [SF_DIR [NAME ...]]` prints them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import minhash, text, weights
from .operators import combo, datagen, edit, evaluate, ranking, scoring
from .operators.index import Queries, TokenIndex, TokenSpec, sample_queries, term_stats, tokenized
from .operators.storage import spread, stored
from .sources import tables

#: Jobs that run at once where none of them is timed: most are short, and one alone leaves cores idle.
AT_ONCE = 4
SIZE, CLEAN, ASKED, TIMED, TIMED_WORDS = 5000, 500, 500, 100, 20

GRAM = {
    "xect": ("xect", {}), "jaccard": ("jaccard", {}), "wm_rs": ("wm", {}), "wj_rs": ("wj", {}), "cosine": ("cosine", {}),
    "bm25": ("bm25", {}), "lm": ("lm", {}), "hmm": ("hmm", {}),
}
SETS = tuple(f"CU{i}" for i in range(1, 9))
WORD = {"edit": ("edit", {}), "ges": ("ges", {}), "soft_tfidf_jw": ("soft_tfidf", {})}
_TABLE = "set string, predicate string, map double, mean_max_f1 double"


def dirty(spark: SparkSession, sf: str, preset: str, size: int = SIZE, clean: int = CLEAN, duplicates: str = "uniform", **other) -> DataFrame:
    """A generated set, stored for the runs over it."""
    base = tables.long_titles(spark, sf) if preset == "timing" else tables.short_names(spark, sf)
    spec = datagen.ErrorSpec(**(vars(datagen.preset(preset, size, clean, duplicates)) | other))
    return stored(datagen.generate_dirty(base, spec))


def accuracy(data: DataFrame, name: str, predicates: dict[str, tuple[str, dict]], asked: int = ASKED, size: int = 2, prune: float = 0.0, seed: int = 42) -> list[tuple]:
    """(set, predicate, map, mean_max_f1) of predicates over one set; full lists, no threshold, the same queries for all.
    Token predicates are scored in one pass, the others once for each different string. One row each, held on the
    driver, so that no plan grows with their number."""
    rel = data.select("tid", "s")
    queries = stored(sample_queries(rel, asked, seed))
    known, truth = Queries(queries, asked), stored(datagen.truth(data, queries))
    grams = {k: v for k, v in predicates.items() if v[0] not in ("edit", "ges", "ges_bound", "ges_select", "soft_tfidf")}
    found = {}

    def judge(scores: DataFrame, labels: list[str]) -> None:
        for r in evaluate.measures(scores, labels, truth, queries).collect():
            found[r["label"]] = (r["map"], r["mean_max_f1"])

    def judge_grams() -> None:
        index = TokenIndex.build(rel, TokenSpec("qgram", size), prune)
        judge(stored(scoring.score_many(index, known, grams)), list(grams))

    words = TokenIndex.build(rel, TokenSpec("word")) if len(grams) < len(predicates) else None

    def judge_one(label: str) -> None:
        predicate, params = predicates[label]

        def scored(index: TokenIndex, heads: Queries) -> DataFrame:
            if predicate == "ges_select":
                return combo.ges_select(index, heads, keep_candidates=True, **params)
            return ranking.score(index, heads, predicate, **params)

        judge(stored(ranking.of_copies(words, known, scored).withColumnRenamed("score", label)), [label])

    with ThreadPoolExecutor(AT_ONCE) as pool:
        runs = [pool.submit(judge_grams)] if grams else []
        runs += [pool.submit(judge_one, label) for label in predicates if label not in grams]
        for run in runs:
            run.result()
    return [(name, label, *found[label]) for label in predicates]


def _frame(spark: SparkSession, rows: Iterable[tuple], schema: str = _TABLE) -> DataFrame:
    return spark.createDataFrame(list(rows), schema)


def _over(sets: Iterable[str], predicates: dict, **options) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf: str, asked: int = ASKED) -> DataFrame:
        return _frame(spark, [r for s in sets for r in accuracy(dirty(spark, sf, s), s, predicates, asked, **options)])

    return run


def q_size(spark: SparkSession, sf: str, asked: int = ASKED) -> DataFrame:
    """q = 2 and 3 on the dirty sets, for four predicates."""
    four = {k: GRAM[k] for k in ("jaccard", "cosine", "hmm", "bm25")}
    rows = []
    for s in datagen.CLASSES["dirty"]:
        data = dirty(spark, sf, s)
        rows += [r for n in (2, 3) for r in accuracy(data, f"{s} q={n}", four, asked, size=n)]
    return _frame(spark, rows)


def map_classes(spark: SparkSession, sf: str, asked: int = ASKED) -> DataFrame:
    """All predicates over CU1-CU8, and their means over the sets of each class."""
    rows = [r for s in SETS for r in accuracy(dirty(spark, sf, s), s, GRAM | WORD, asked)]
    kind = {s: f"class {c}" for c, some in datagen.CLASSES.items() for s in some}
    table = _frame(spark, [(x, *r[1:]) for r in rows for x in (r[0], kind[r[0]])])
    return table.groupBy("set", "predicate").agg(F.round(F.avg("map"), 6).alias("map"), F.round(F.avg("mean_max_f1"), 6).alias("mean_max_f1"))


def pruning(spark: SparkSession, sf: str, asked: int = ASKED, timed: int = TIMED) -> DataFrame:
    """MAP of all token predicates by pruning rate, the token rows that stay, and seconds for 100 queries."""
    data = dirty(spark, sf, "CU1")
    some = Queries(stored(sample_queries(data.select("tid", "s"), timed)), timed)
    rows = []
    for rate in (0.0, 0.1, 0.2, 0.3, 0.4, 0.5):
        index = TokenIndex.build(data.select("tid", "s"), TokenSpec(), rate)
        scoring.score_many(index, some, GRAM).write.format("noop").mode("overwrite").save()  # sums of weights are stored
        seconds = evaluate.timed(lambda index=index: scoring.score_many(index, some, GRAM))
        n = index.postings.count()
        rows += [(rate, label, map_, f1, n, round(seconds, 3)) for _, label, map_, f1 in accuracy(data, "CU1", GRAM, asked, prune=rate)]
    return _frame(spark, rows, "rate double, predicate string, map double, mean_max_f1 double, token_rows long, seconds_all double")


def idf_hist(spark: SparkSession, sf: str) -> DataFrame:
    """Tokens and token rows by idf at q = 3 on the dirtiest set, and the token rows that the rate 0.33 drops."""
    index = TokenIndex.build(dirty(spark, sf, "CU1").select("tid", "s"), TokenSpec("qgram", 3))
    return evaluate.idf_histogram(index, 20, 0.33).select("bin", F.round("low", 6).alias("low"), "tokens", "postings", "dropped")


def minhash_error(spark: SparkSession, sf: str, asked: int = ASKED, timed: int = TIMED) -> DataFrame:
    """hashes, mean absolute error of the estimate of the words' Jaccard similarity, and of the filter by min-hash on the
    dirtiest set: MAP of its scores, seconds for 100 queries."""
    w = tables.load(spark, sf, "part").select(F.col("p_name").alias("w")).distinct()
    g = w.select("w", F.array_distinct(text.qgrams(F.col("w"), 2)).alias("g"))
    pairs = g.alias("a").join(g.alias("b"), F.col("a.w") < F.col("b.w")).select(F.col("a.g").alias("x"), F.col("b.g").alias("y"))
    exact = F.size(F.array_intersect("x", "y")) / F.size(F.array_union("x", "y")).cast("double")
    sizes = (1, 2, 3, 5, 8, 16)
    guess = lambda h: minhash.minhash_similarity(minhash.minhash_signature(F.col("x"), h), minhash.minhash_signature(F.col("y"), h))
    error = pairs.agg(*(F.round(F.avg(F.abs(guess(h) - exact)), 6).alias(f"e{h}") for h in sizes)).first()
    data = dirty(spark, sf, "CU1")
    found = {r[1]: r[2] for r in accuracy(data, "CU1", {f"{h}": ("ges_bound", {"sim": "minhash", "hashes": h}) for h in sizes}, asked)}
    index = TokenIndex.build(data.select("tid", "s"), TokenSpec("word"))
    some = Queries(stored(sample_queries(data.select("tid", "s"), timed)), timed)
    return _frame(spark, [(h, error[f"e{h}"], found[f"{h}"], round(evaluate.timed(lambda h=h: combo.score_ges_bound(index, some, "minhash", hashes=h)), 3)) for h in sizes], "hashes int, error double, map double, seconds double")


def case_study(spark: SparkSession, sf: str) -> DataFrame:
    """Ranks of the true matches of one clean tuple, by predicate."""
    data = dirty(spark, sf, "CU5")
    rel = data.select("tid", "s")
    query = data.where("is_clean").orderBy("tid").limit(1).select(F.col("tid").alias("qid"), "s")
    truth = datagen.truth(data, query)
    grams, words, out = TokenIndex.build(rel), TokenIndex.build(rel, TokenSpec("word")), None
    for label, (predicate, params) in (GRAM | WORD).items():
        index = words if predicate in ("ges", "soft_tfidf") else grams
        params = params | {"log": True} if predicate in ("lm", "hmm") else params
        ranked = ranking.rank_all(ranking.score(index, Queries(query, 1), predicate, **params))
        one = ranked.join(truth, ["qid", "tid"]).select(F.lit(label).alias("predicate"), "tid", "rank")
        out = one if out is None else out.unionByName(one)
    return out


def distributions(spark: SparkSession, sf: str, asked: int = ASKED) -> DataFrame:
    """All token predicates by distribution of duplicates and size of the set."""
    return _frame(spark, [r for size, clean in ((SIZE, CLEAN), (4 * SIZE, 4 * CLEAN)) for kind in ("uniform", "zipf", "poisson") for r in accuracy(dirty(spark, sf, "CU6", size, clean, kind), f"CU6 {kind} {size}", GRAM, asked)])


def error_rate(spark: SparkSession, sf: str, asked: int = ASKED) -> DataFrame:
    """Token predicates on the single-error sets, by share of erroneous duplicates."""
    return _frame(spark, [r for s in ("F1", "F2", "F4") for share in (0.1, 0.5, 0.9) for r in accuracy(dirty(spark, sf, s, erroneous=share), f"{s} {share}", GRAM, asked)])


def weight_pruning(spark: SparkSession, sf: str, asked: int = ASKED, timed: int = TIMED) -> DataFrame:
    """MAP of BM25 and cosine with and without the weights below mean - sd / 2, and seconds for 100 queries, on a set
    of each class."""
    rows = []
    for s in ("CU1", "CU5", "CU8"):
        data = dirty(spark, sf, s)
        rel = data.select("tid", "s")
        queries = stored(sample_queries(rel, asked))
        truth, index = stored(datagen.truth(data, queries)), TokenIndex.build(rel)
        for predicate in ("bm25", "cosine"):
            w = stored(scoring.base_weights(index, predicate))
            wq = stored(scoring.query_weights(index, Queries(queries, asked), predicate))
            few = stored(scoring.query_weights(index, Queries(stored(sample_queries(rel, timed)), timed), predicate))
            for label, kept in ((predicate, w), (f"{predicate} pruned", stored(scoring.prune_by_weight(w, "avg-0.5sd", predicate)))):
                one = evaluate.measures(scoring.score_weighted_sum(kept, wq).withColumnRenamed("score", label), [label], truth, queries).first()
                rows.append((s, label, one["map"], kept.count(), round(evaluate.timed(lambda kept=kept, few=few: scoring.score_weighted_sum(kept, few)), 3)))
    return _frame(spark, rows, "set string, predicate string, map double, token_rows long, seconds double")


def ges_theta(spark: SparkSession, sf: str, asked: int = ASKED) -> DataFrame:
    """MAP of exact generalised edit similarity behind its filters, by threshold, and the share of pairs that the filter
    leaves (C / N)."""
    data = dirty(spark, sf, "CU1")
    rel = data.select("tid", "s")
    words, n = TokenIndex.build(rel, TokenSpec("word")), rel.count()
    known = Queries(stored(sample_queries(rel, asked)), asked)
    rows = [(*r[1:], 1.0) for r in accuracy(data, "CU1", {"ges": ("ges", {})}, asked)]
    for f in ("jaccard", "minhash"):
        bound = stored(combo.score_ges_bound(words, known, f))
        for t in (0.7, 0.8, 0.9):
            share = bound.where(F.col("score") >= t - 1e-12).count() / (asked * n)
            rows += [(*r[1:], round(share, 6)) for r in accuracy(data, "CU1", {f"ges_{f} {t}": ("ges_select", {"filter": f, "theta": t})}, asked)]
    return _frame(spark, rows, "predicate string, map double, mean_max_f1 double, share double")


def passages(spark: SparkSession, sf: str) -> DataFrame:
    """MAP of finding the documents that hold a benchmark passage, among the passages that some document holds."""
    docs, asked = tables.doc_text(spark, sf).where("s is not null"), tables.passages(spark, sf)
    index = TokenIndex.build(docs, TokenSpec("word"))
    # a document that holds a passage shares all its words: the postings find the pairs, the strings decide
    n = asked.count()
    scores = stored(scoring.score_many(index, Queries(asked, n), {k: GRAM[k] for k in ("jaccard", "cosine", "bm25", "lm", "hmm")} | {"shared": ("xect", {})}))
    size = asked.select("qid", F.size(F.array_distinct(text.words(F.col("s")))).alias("words"), F.col("s").alias("q"))
    near = scores.join(size, "qid").where("shared >= words").select("qid", "tid", "q").join(docs, "tid")
    truth = stored(near.where(F.contains("s", "q")).select("qid", "tid"))
    queries = truth.select("qid").distinct()
    labels = ["jaccard", "cosine", "bm25", "lm", "hmm"]
    return evaluate.measures(scores.join(queries, "qid", "left_semi"), labels, truth, queries)


# ---- times ------------------------------------------------------------------------------------------------------------


def timing_set(spark: SparkSession, sf: str, size: int) -> DataFrame:
    """tid, s of `size` titles, from a tenth as many clean ones or all there are."""
    n = min(size // 10, tables.long_titles(spark, sf).count())
    return dirty(spark, sf, "timing", size, n).select("tid", "s")


def bench_preprocess(spark: SparkSession, sf: str, size: int = 10_000) -> DataFrame:
    """Seconds of the two phases of preprocessing by predicate: tokens, then weights (which need the tokens' statistics)."""
    rel = spread(timing_set(spark, sf, size)).cache()
    rel.count()
    bag = lambda kind: tokenized(rel, TokenSpec(kind))
    distinct = lambda: rel.select("tid", F.array_distinct(text.qgrams(F.col("s"), 2)).alias("t"))
    grams, words = TokenIndex.build(rel), TokenIndex.build(rel, TokenSpec("word"))
    stats = lambda i: term_stats(i.rows)
    of_words = lambda: bag("word").select("tid", F.explode("bag").alias("x")).select("tid", "x.token").distinct().select("token", text.qgrams(F.col("token"), 2).alias("g"))
    sums = lambda i, **c: i.with_stats().groupBy("tid").agg(*(F.sum(x).alias(k) for k, x in c.items()))
    comp = F.log1p(-weights.lm_prob(F.col("tf"), F.col("dl"), F.col("sum_pml"), F.col("df")))
    vocabulary = words.stats.select(F.col("token").alias("w"), text.qgrams(F.col("token"), 2).alias("g"))
    none = None
    phases = {
        "xect": (distinct, none), "jaccard": (distinct, none), "edit": (lambda: rel.select("tid", text.edit_grams(F.col("s"), 2).alias("g")), none),
        "wm_rs": (lambda: bag("qgram"), lambda: stats(grams).withColumn("w", weights.rs_weight(grams.n(), F.col("df")))),
        "wj_rs": (lambda: bag("qgram"), lambda: sums(grams, wlen=weights.rs_weight(grams.n(), F.col("df")))),
        "cosine": (lambda: bag("qgram"), lambda: scoring.base_weights(grams, "cosine")),
        "bm25": (lambda: bag("qgram"), lambda: scoring.base_weights(grams, "bm25")),
        "lm": (lambda: bag("qgram"), lambda: sums(grams, comp=comp)),
        "hmm": (lambda: bag("qgram"), lambda: grams.with_stats().withColumn("w", weights.hmm_weight(F.col("tf"), F.col("dl"), F.col("cf"), grams.cs()))),
        "ges_jaccard": (of_words, lambda: vocabulary.select("w", F.explode(F.array_distinct("g")).alias("token"))),
        "ges_minhash": (of_words, lambda: vocabulary.select("w", minhash.minhash_signature(F.array_distinct("g"), 5).alias("signature"))),
        "soft_tfidf_jw": (lambda: bag("word"), lambda: scoring.base_weights(words, "cosine")),
    }
    evaluate.timed(lambda: bag("qgram"))  # code generation
    rows = [(name, round(evaluate.timed(first), 3), round(evaluate.timed(second), 3) if second else 0.0) for name, (first, second) in phases.items()]
    rel.unpersist()
    return _frame(spark, rows, "predicate string, tokenise double, weigh double")


def _timed_predicates(grams: TokenIndex, words: TokenIndex) -> dict[str, Callable[[Queries], DataFrame]]:
    log = {"lm": {"log": True}, "hmm": {"log": True}}
    out = {k: (lambda q, p=p, v=v: ranking.score(grams, q, p, **v, **log.get(p, {}))) for k, (p, v) in GRAM.items()}
    for f in ("jaccard", "minhash"):
        out[f"ges_{f}"] = lambda q, f=f: combo.ges_select(words, q, 0.8, f)
    return out | {"soft_tfidf_jw": lambda q: combo.score_soft_tfidf(words, q), "edit": lambda q: edit.edit_select(grams.rows.select("tid", "s"), q, 0.7)}


def _asked(rel: DataFrame, asked: int, cut: int | None = None) -> dict[bool, Queries]:
    """The queries to time: `asked`, and TIMED_WORDS of them for the predicates over words."""
    s = F.col("s") if cut is None else F.array_join(F.slice(text.words(F.col("s")), 1, cut), " ")
    return {few: Queries(stored(sample_queries(rel, n).withColumn("s", s)), n) for few, n in ((False, asked), (True, min(asked, TIMED_WORDS)))}


def _ms(scores: dict[str, Callable[[Queries], DataFrame]], queries: dict[bool, Queries]) -> dict[str, float]:
    """Milliseconds a query by predicate. All run twice: once for code generation and sums of weights, which are
    preprocessing, several at once; then each alone, and timed."""
    of = {name: queries[name.startswith(("ges", "soft"))] for name in scores}
    with ThreadPoolExecutor(AT_ONCE) as pool:
        list(pool.map(lambda name: evaluate.timed(lambda: scores[name](of[name])), scores))
    return {name: round(evaluate.timed(lambda name=name: scores[name](of[name])) * 1000 / of[name].rows, 3) for name in scores}


def bench_query(spark: SparkSession, sf: str, size: int = 10_000, asked: int = TIMED) -> DataFrame:
    """Milliseconds a query by predicate, the mean of 100 queries (20 for words) asked together: preparing and scoring."""
    rel = timing_set(spark, sf, size)
    grams, words = TokenIndex.build(rel), TokenIndex.build(rel, TokenSpec("word"))
    queries = _asked(rel, asked)
    return _frame(spark, _ms(_timed_predicates(grams, words), queries).items(), "predicate string, ms double")


def bench_scale(spark: SparkSession, sf: str, sizes: tuple[int, ...] = (10_000, 30_000, 100_000), asked: int = TIMED) -> DataFrame:
    """Milliseconds a query of three words, by predicate and size of the set; edit similarity is left out."""

    def ready(size: int) -> tuple[dict[str, Callable[[Queries], DataFrame]], dict[bool, Queries]]:
        rel = timing_set(spark, sf, size)
        scores = _timed_predicates(TokenIndex.build(rel), TokenIndex.build(rel, TokenSpec("word")))
        return {name: score for name, score in scores.items() if name != "edit"}, _asked(rel, asked, 3)

    with ThreadPoolExecutor(AT_ONCE) as pool:
        sets = list(pool.map(ready, sizes))
    rows = [(size, name, ms) for size, (scores, queries) in zip(sizes, sets, strict=True) for name, ms in _ms(scores, queries).items()]
    return _frame(spark, rows, "size int, predicate string, ms double")


_SOFT = {f"{s} {t}": ("soft_tfidf", {"word_sim": s, "theta": t}) for s, ts in (("jaro_winkler", (0.7, 0.8, 0.9)), ("edit", (0.5, 0.7, 0.8)), ("jaccard", (0.3, 0.5, 0.7)), ("intersect", (2.0, 3.0, 4.0))) for t in ts}
_A0 = {f"hmm a0={a}": ("hmm", {"a0": a}) for a in (0.05, 0.1, 0.2, 0.35, 0.5, 0.7, 0.95)}

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "exp_q_size": q_size,
    "exp_weights": _over((*SETS, "F1", "F2", "F3", "F4", "F5"), {"wm_rs": ("wm", {}), "wm_idf": ("wm", {"weights": "idf"}), "wj_rs": ("wj", {}), "wj_idf": ("wj", {"weights": "idf"})}),
    "exp_single_errors": _over(("F1", "F2"), GRAM | WORD),
    "exp_edit_extent": _over(("F3", "F4", "F5"), GRAM | WORD),
    "exp_map_classes": map_classes,
    "exp_case_study": case_study,
    "exp_ges_theta": ges_theta,
    "exp_minhash": minhash_error,
    "exp_soft_inner": _over(("CU1",), _SOFT),
    "exp_hmm_a0": _over(("CU1",), _A0),
    "exp_pruning": pruning,
    "exp_idf_hist": idf_hist,
    "exp_distributions": distributions,
    "exp_error_rate": error_rate,
    "exp_weight_prune": weight_pruning,
    "exp_passages": passages,
    "bench_preprocess": bench_preprocess,
    "bench_query": bench_query,
    "bench_scale": bench_scale,
}


def lm_forms(spark: SparkSession, sf: str, asked: int = ASKED) -> DataFrame:
    """MAP of the language model restricted to shared tokens and in full, on a set of each class."""
    rows = []
    for s in ("CU1", "CU5", "CU8"):
        data = dirty(spark, sf, s)
        queries = stored(sample_queries(data.select("tid", "s"), asked))
        truth, index = stored(datagen.truth(data, queries)), TokenIndex.build(data.select("tid", "s"))
        for form in ("restricted", "full"):
            scores = scoring.score_lm(index, Queries(queries, asked), form, log=True).withColumnRenamed("score", form)
            rows.append((s, f"lm {form}", *evaluate.measures(scores, [form], truth, queries).select("map", "mean_max_f1").first()))
    return _frame(spark, rows)


QUERIES["exp_lm_forms"] = lm_forms


def main(args: list[str]) -> None:
    spark = SparkSession.builder.master("local[*]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    sf, names = args[0] if args else "/root/testdata/sf0.01", args[1:] or list(QUERIES)
    for name in names:
        print(name)
        QUERIES[name](spark, sf).show(200, truncate=False)
    spark.stop()


if __name__ == "__main__":
    import sys

    main(sys.argv[1:])

__all__ = ["QUERIES", "accuracy", "dirty"]
