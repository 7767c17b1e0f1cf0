"""What the registered accuracy workloads cover."""

from approxmatch import experiments


def test_registered_workloads_are_whole(spark, monkeypatch):
    """Sets, predicates and queries of the registered calls, and the class means, without running a predicate."""
    calls = []

    def accuracy(data, name, predicates, asked=experiments.ASKED, **options):
        calls.append((name, tuple(predicates), asked))
        place = int(data[2:]) if data.startswith("CU") else 0
        return [(name, p, place / 10, place / 20) for p in predicates]

    monkeypatch.setattr(experiments, "dirty", lambda spark, sf, preset, *shape, **options: preset)
    monkeypatch.setattr(experiments, "accuracy", accuracy)
    cu = [f"CU{i}" for i in range(1, 9)]
    every = {"xect", "jaccard", "wm_rs", "wj_rs", "cosine", "bm25", "lm", "hmm", "edit", "ges", "soft_tfidf_jw"}
    got = {(r["set"], r["predicate"]): r["map"] for r in experiments.QUERIES["exp_map_classes"](spark, "").collect()}
    assert [c[0] for c in calls] == cu and all(set(c[1]) == every and c[2] == 500 for c in calls)
    assert {s for s, _ in got} == {*cu, "class dirty", "class medium", "class low"} and len(got) == 11 * len(every)
    assert (got["class dirty", "ges"], got["class medium", "ges"], got["class low", "ges"]) == (0.15, 0.45, 0.75)
    for name, sets, predicates in (("exp_q_size", 4, 4), ("exp_weights", 13, 4), ("exp_edit_extent", 3, 11), ("exp_soft_inner", 1, 12), ("exp_hmm_a0", 1, 7), ("exp_distributions", 6, 8), ("exp_error_rate", 9, 8)):
        calls.clear()
        experiments.QUERIES[name](spark, "")
        assert len(calls) == sets and all(len(c[1]) == predicates and c[2] == 500 for c in calls)


def test_measures_equal_whole_rankings(spark, sf):
    """MAP and mean maximal F1 from the ranks of relevant tuples alone, of predicates scored in one pass, are those of
    whole rankings of each predicate; and the orders that hold on data with few errors are found."""
    from approxmatch.operators import datagen, evaluate, ranking
    from approxmatch.operators.index import Queries, TokenIndex, sample_queries

    data = experiments.dirty(spark, sf, "CU5", 300, 30)
    rel = data.select("tid", "s")
    got = {r[1]: r[2:] for r in experiments.accuracy(data, "CU5", experiments.GRAM | {"edit": ("edit", {})}, 40)}
    queries = sample_queries(rel, 40)
    truth, index = datagen.truth(data, queries), TokenIndex.build(rel)
    for label in ("jaccard", "bm25", "lm", "edit"):
        predicate, params = (experiments.GRAM | {"edit": ("edit", {})})[label]
        ranked = ranking.rank_all(ranking.score(index, Queries(queries, 40), predicate, **params, **({"log": True} if label == "lm" else {})))
        assert abs(got[label][0] - evaluate.mean_average_precision(ranked, truth, queries).first()[0]) < 1e-5
        assert abs(got[label][1] - evaluate.mean_max_f1(ranked, truth, queries).first()[0]) < 1e-5
    assert got["bm25"][0] > got["xect"][0] and got["bm25"][0] > got["edit"][0] and got["wm_rs"][0] > got["xect"][0]


def test_jaro_winkler_bound(spark):
    from pyspark.sql import functions as F

    from approxmatch.functions import strsim

    words = ["", "a", "martha", "marhta", "dixon", "dicksonx", "abcd", "abce", "zz", "aaaa", "aab", "é", "éa"]
    pairs = spark.createDataFrame([(x, y) for x in words for y in words], "a string, b string")
    rows = pairs.select("a", "b", strsim.jaro_winkler_bound(F.col("a"), F.col("b")).alias("bound")).collect()
    assert all(r.bound >= strsim.jaro_winkler_of(r.a, r.b) - 1e-12 for r in rows)
    assert sum(r.bound < 0.8 for r in rows) > len(rows) // 3


def test_heavy_steps_are_spread(spark, sf):
    """Few rows with much work each: generated strings, alignments and pairs of words stand in more than one task."""
    from approxmatch.operators import combo
    from approxmatch.operators.index import Queries, TokenIndex, TokenSpec, sample_queries

    rel = experiments.dirty(spark, sf, "CU5", 300, 30).select("tid", "s")
    assert rel.rdd.getNumPartitions() > 1
    words = TokenIndex.build(rel, TokenSpec("word"))
    queries = Queries(sample_queries(rel, 5), 5)
    asked = combo.query_word_idf(words, queries)
    found = combo.score_ges_bound(words, queries).where("score >= 0.8")
    assert combo.score_ges(words, queries).rdd.getNumPartitions() > 1
    assert combo.score_ges(words, queries, pairs=found).rdd.getNumPartitions() > 1
    for sim in ("jaro_winkler", "edit"):
        assert combo.word_pairs(words, asked, queries.tokens, sim, above=0.8).rdd.getNumPartitions() > 1


def test_letter_mask_bound_loses_no_pair(spark):
    """The bound by letter masks is never below Jaro-Winkler, and rules out most pairs of different words."""
    from pyspark.sql import functions as F

    from approxmatch.functions import strsim

    words = ["", "a", "martha", "marhta", "dixon", "dicksonx", "abcd", "abce", "zz", "aaaa", "aab", "é", "éa", "Aa", "\U0001f600a", "x-1", "11", "mississippi", "misisipi"]
    pairs = spark.createDataFrame([(x, y) for x in words for y in words], "a string, b string")
    a, b = F.col("a"), F.col("b")
    rows = pairs.select("a", "b", strsim.jaro_winkler_bound(a, b).alias("near"), strsim.jaro_winkler_mask_bound(a, b, strsim.letter_mask(a), strsim.letter_mask(b)).alias("bound")).collect()
    assert all(r.bound >= strsim.jaro_winkler_of(r.a, r.b) - 1e-12 and r.bound >= r.near - 1e-12 for r in rows)
    assert sum(r.bound < 0.8 for r in rows) > len(rows) // 3


def test_scale_times_every_predicate_and_size(spark, sf):
    """The whole table: each size and each predicate but edit similarity, timed after a run that isn't."""
    rows = experiments.bench_scale(spark, sf, (60, 90), 5).collect()
    names = {*experiments.GRAM, "ges_jaccard", "ges_minhash", "soft_tfidf_jw"}
    assert [(r["size"], r["predicate"]) for r in rows] == [(s, p) for s in (60, 90) for p in experiments._timed_predicates(None, None) if p != "edit"]
    assert {r["predicate"] for r in rows} == names and all(r["ms"] > 0 for r in rows)


def test_counted_ranks_are_those_of_sorting(spark, monkeypatch):
    """Ties within the rounding, missing and infinite scores, unreturned relevant tuples: counted and sorted ranks agree,
    and so do the measures where some queries are counted and others sorted. Counting sorts no pair."""
    from approxmatch.operators import evaluate

    inf, tiny = float("inf"), 1e-10
    rows = [(q, t, (t * 7 % 11) / 4 + (t % 3) * tiny, None if t % 5 == 0 else float(t % 4), inf if t % 6 == 0 else -0.5) for q in (1, 2, 3) for t in range(40)]
    scores = spark.createDataFrame(rows, "qid long, tid long, a double, `b c` double, d double")
    truth = spark.createDataFrame([(1, 3), (1, 10), (1, 12), (1, 99), *((2, t) for t in range(0, 40, 3)), (4, 1)], "qid long, tid long")
    queries = spark.createDataFrame([(q,) for q in (1, 2, 3, 4)], "qid long")
    labels = ["a", "b c", "d"]
    counted, ordered = (sorted(map(tuple, f(scores, labels, truth, 9).select("qid", "tid", "label", "rank").collect())) for f in (evaluate._counted_ranks, evaluate._sorted_ranks))
    assert counted == ordered and len(counted) == 3 * 17 - 1 - 3
    found = []
    for most in (0, 5, 64):
        monkeypatch.setattr(evaluate, "FEW_RELEVANT", most)
        found.append(sorted(map(tuple, evaluate.measures(scores, labels, truth, queries).collect())))
    assert found[0] == found[1] == found[2] and len(found[0]) == 3


def test_word_predicates_get_all_queries(spark, sf):
    """Measures of word predicates are those of whole rankings for every query, with copies among tuples and queries."""
    from approxmatch.operators import datagen, evaluate, ranking
    from approxmatch.operators.index import Queries, TokenIndex, TokenSpec, sample_queries

    data = experiments.dirty(spark, sf, "CU7", 140, 12).cache()
    rel, n = data.select("tid", "s"), 110
    assert rel.select("s").distinct().count() < 140
    got = {r[1]: r[2:] for r in experiments.accuracy(data, "CU7", {"ges": ("ges", {}), "soft": ("soft_tfidf", {})}, n)}
    queries = sample_queries(rel, n)
    truth, index = datagen.truth(data, queries), TokenIndex.build(rel, TokenSpec("word"))
    for label, predicate in (("ges", "ges"), ("soft", "soft_tfidf")):
        ranked = ranking.rank_all(ranking.score(index, Queries(queries, n), predicate))
        assert abs(got[label][0] - evaluate.mean_average_precision(ranked, truth, queries).first()[0]) < 1e-5
        assert abs(got[label][1] - evaluate.mean_max_f1(ranked, truth, queries).first()[0]) < 1e-5
