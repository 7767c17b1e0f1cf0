import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from reference_impl import grams

from approxmatch.functions import minhash, strsim, text


def test_grams_words_bags(spark):
    rows = [(1, "db lab"), (2, ""), (3, None), (4, "  a  b "), (5, "日本 é")]
    df = spark.createDataFrame(rows, "i long, s string")
    out = df.select("i", text.qgrams(F.col("s"), 2).alias("g2"), text.qgrams(F.col("s"), 3).alias("g3"), text.words(F.col("s")).alias("w"), text.qgrams(F.col("s"), 1).alias("g1")).collect()
    for r, (_, s) in zip(sorted(out), rows, strict=True):
        assert r.g2 == grams(s) and r.g3 == grams(s, 3) and r.w == (s or "").split()
        assert r.g1 == list("".join((s or "").split()))
    bag = df.select(text.token_bag(text.qgrams(F.concat_ws(" ", "s", "s"), 2)).alias("b")).first().b
    assert {x.token: x.tf for x in bag} == {"$d": 2, "db": 2, "b$": 4, "$l": 2, "la": 2, "ab": 2}
    assert [len(r.g) for r in df.select(text.edit_grams(F.col("s"), 3).alias("g")).collect()] == [8, 0, 0, 9, 6]


@pytest.mark.parametrize(("a", "b", "want"), [("MARTHA", "MARHTA", 0.961111), ("DIXON", "DICKSONX", 0.813333), ("ab", "ac", 0.666667), ("inc", "incorporated", 0.825), ("gear", "geer", 0.866667)])
def test_jaro_winkler(a, b, want):
    assert strsim.jaro_winkler_of(a, b) == pytest.approx(want, abs=1e-6)


def test_costs():
    assert strsim.edit_cost_of("kitten", "sitting") == 3
    assert strsim.edit_cost_of("ab", "ba") == 2 and strsim.edit_cost_of("ab", "ba", swap=1.0) == 1
    assert strsim.edit_cost_of("", "abc", insert=0.5) == 1.5


@given(st.text("ab", max_size=8), st.text("ab", max_size=8))
@settings(max_examples=200, deadline=None)
def test_bag_bound_is_above_edit_similarity(a, b):
    from collections import Counter

    if not a or not b:
        return
    x, y = Counter(grams(a)), Counter(grams(b))
    both = sum((x & y).values())
    jaccard = both / (sum(x.values()) + sum(y.values()) - both)
    edit = 1 - strsim.edit_cost_of(a, b) / max(len(a), len(b))
    assert jaccard + 1 - 1 / 2 >= edit - 1e-9
    longer = max(len(a), len(b))
    k = int(strsim.edit_cost_of(a, b))
    assert both >= longer + 1 - 2 * k


def test_minhash_is_close_to_jaccard(spark):
    df = spark.createDataFrame([("incorporated", "incorporation")], "a string, b string")
    x, y = (F.array_distinct(text.qgrams(F.col(c), 2)) for c in "ab")
    row = df.select(minhash.minhash_similarity(minhash.minhash_signature(x, 256), minhash.minhash_signature(y, 256)).alias("m"), (F.size(F.array_intersect(x, y)) / F.size(F.array_union(x, y))).alias("j")).first()
    assert abs(row.m - row.j) < 3 * (row.j * (1 - row.j) / 256) ** 0.5 + 1e-9
