import pytest
from pyspark.sql import functions as F

from approxmatch.operators import datagen, evaluate
from approxmatch.operators.index import TokenIndex
from approxmatch.sources import tables


def test_measures_by_hand(spark):
    ranked = spark.createDataFrame([(1, t, t) for t in range(1, 6)], "qid long, tid long, rank int")
    truth = spark.createDataFrame([(1, 1), (1, 3), (1, 4), (1, 99), (2, 7)], "qid long, tid long")
    queries = spark.createDataFrame([(1,), (2,)], "qid long")
    ap = {r.qid: r.ap for r in evaluate.average_precision(ranked, truth, queries).collect()}
    assert ap == pytest.approx({1: (1 + 2 / 3 + 3 / 4) / 4, 2: 0.0})
    f1 = {r.qid: r.f1 for r in evaluate.max_f1(ranked, truth, queries).collect()}
    assert f1 == pytest.approx({1: 0.75, 2: 0.0})
    assert evaluate.mean_average_precision(ranked, truth, queries).first()[0] == pytest.approx(ap[1] / 2)


def clean(spark, n=100):
    return spark.range(n).select(F.col("id").alias("tid"), F.concat(F.lit("some words here "), F.col("id").cast("string"), F.lit(" Inc.")).alias("s"))


def test_generator_shares_and_repeatability(spark):
    spec = datagen.preset("CU2", 1000, 100)
    one = datagen.generate_dirty(clean(spark), spec).collect()
    two = datagen.generate_dirty(clean(spark).repartition(7), spec).collect()
    assert sorted(one) == sorted(two)
    assert len(one) == 1000 and sum(r.is_clean for r in one) == 100
    wrong = sum(r.is_erroneous for r in one) / 900
    assert 0.44 < wrong < 0.56
    by_tid = {r.cluster_id: r.s for r in one if r.is_clean}
    assert all(r.s == by_tid[r.cluster_id] for r in one if not r.is_erroneous)


def test_generator_edits(spark):
    from approxmatch.functions.strsim import edit_cost_of

    rows = datagen.generate_dirty(clean(spark), datagen.preset("F4", 400, 100)).collect()
    base = {r.cluster_id: r.s for r in rows if r.is_clean}
    for r in rows:
        if r.is_erroneous:
            n = len(base[r.cluster_id])
            assert edit_cost_of(base[r.cluster_id], r.s) <= 2 * round(0.2 * n)
    swapped = datagen.generate_dirty(clean(spark), datagen.preset("F2", 400, 100)).collect()
    assert all(sorted(r.s.split()) == sorted(base[r.cluster_id].split()) for r in swapped)
    forms = datagen.generate_dirty(clean(spark), datagen.preset("F1", 400, 100)).collect()
    assert {r.s.split()[-1] for r in forms} == {"Inc.", "Incorporated"}


def test_files_of_every_format(spark, tmp_path):
    rel = spark.createDataFrame([(1, "a b"), (2, "c")], "tid long, s string").coalesce(1)
    for fmt in tables.FORMATS:
        tables.write_relation(rel, f"{tmp_path}/{fmt}", fmt)
        got = tables.read_relation(spark, f"{tmp_path}/{fmt}", fmt)
        assert sorted(r.s for r in got.collect()) == ["a b", "c"]
    tables.write_scores(spark.createDataFrame([(1, 2, 0.5)], "qid long, tid long, score double"), f"{tmp_path}/scores")
    assert spark.read.parquet(f"{tmp_path}/scores").count() == 1


def test_histogram_counts_everything(spark, sf):
    index = TokenIndex.build(tables.part_desc(spark, sf))
    h = evaluate.idf_histogram(index, 5, 0.3).collect()
    assert sum(r.tokens for r in h) == index.meta.vocabulary
    assert sum(r.postings for r in h) == index.postings.count()


def test_classes_as_truth(spark):
    """Classes give what their listed pairs give; the function's mean counts the relevant tuples beyond the cut."""
    from approxmatch import catalog

    marks = spark.createDataFrame([(i, "ab"[i % 2]) for i in range(10)], "tid long, class string")
    classes = evaluate.Classes(marks.withColumnRenamed("tid", "qid"), marks)
    pairs = classes.queries.join(marks, "class").select("qid", "tid")
    ranked = spark.createDataFrame([(i, (i + k) % 10, k + 1) for i in range(10) for k in range(3)], "qid long, tid long, rank int")
    asked = marks.select(marks.tid.alias("qid"))
    ap = lambda t: {r.qid: round(r.ap, 9) for r in evaluate.average_precision(ranked, t, asked).collect()}
    assert ap(classes) == ap(pairs) == dict.fromkeys(range(10), round((1 + 2 / 3) / 5, 9))
    assert {r.qid: r.ap for r in catalog._ap_by_udf(ranked, classes, asked).collect()} == dict.fromkeys(range(10), 0.333333)
    copies = spark.createDataFrame([(0, 3), (1, 1)], "qid long, copies long")
    half = ranked.where("qid <> 1")
    assert evaluate.mean_average_precision(half, classes, copies.select("qid"), copies).first()[0] == pytest.approx(0.25)


def test_near_duplicates_of_a_large_group(spark):
    """A band's rows that come in several frames have one first tuple, the earliest of all."""
    from approxmatch.streaming import streams

    rows = spark.createDataFrame([(t,) for t in (9, 7, 8, 3, 5, 1, 2)], "tid long").coalesce(1)
    arriving = streams.in_order(rows.select("tid", F.lit("x").alias("band"), F.timestamp_seconds(F.lit(1_700_000_000)).alias("ts")), [F.lit(True)])
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "2")
    try:
        got = streams.available(streams.near_duplicates(arriving, lambda r: r.select("band", "tid", "ts"))).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert sorted((r.tid, r["first"]) for r in got) == [(t, 1) for t in (2, 3, 5, 7, 8, 9)]
