"""String similarity: edit distance with unit or other costs, Jaro and Jaro-Winkler, word alignment.

Unit-cost distance is Spark's own `levenshtein`. Jaro-Winkler and other cost models have no native form; they run
as Arrow-batched UDFs over *different* pairs of words or over candidates only.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from .text import let


def edit_similarity(a: Column, b: Column) -> Column:
    """1 - distance / longer length; 1 for two empty strings."""
    longer = F.greatest(F.length(a), F.length(b))
    return F.when(longer == 0, F.lit(1.0)).otherwise(1.0 - F.levenshtein(a, b).cast("double") / F.greatest(longer, F.lit(1)))


def jaro_of(a: str, b: str) -> float:
    """Jaro similarity of two strings: matches within half the longer length, and half the transpositions."""
    if a == b:
        return 1.0
    n, m = len(a), len(b)
    if not n or not m:
        return 0.0
    reach = max(max(n, m) // 2 - 1, 0)
    used, mine = [False] * m, []
    for i, c in enumerate(a):
        for j in range(max(0, i - reach), min(m, i + reach + 1)):
            if not used[j] and b[j] == c:
                used[j] = True
                mine.append(c)
                break
    k = len(mine)
    if not k:
        return 0.0
    theirs = [c for c, u in zip(b, used, strict=True) if u]
    swapped = sum(x != y for x, y in zip(mine, theirs, strict=True)) // 2
    return (k / n + k / m + (k - swapped) / k) / 3


def jaro_winkler_of(a: str, b: str, scale: float = 0.1, max_prefix: int = 4, boost_above: float = 0.7) -> float:
    """Jaro, raised by the common beginning where it is above boost_above."""
    j = jaro_of(a, b)
    if j <= boost_above:
        return j
    k = 0
    while k < min(len(a), len(b), max_prefix) and a[k] == b[k]:
        k += 1
    return j + k * scale * (1 - j)


def jaro(a: Column, b: Column) -> Column:
    @F.pandas_udf("double")
    def run(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([None if p is None or q is None else jaro_of(p, q) for p, q in zip(x, y, strict=True)], dtype="float64")

    return run(a, b)


def jaro_winkler(a: Column, b: Column, scale: float = 0.1, max_prefix: int = 4, boost_above: float = 0.7) -> Column:
    @F.pandas_udf("double")
    def run(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([None if p is None or q is None else jaro_winkler_of(p, q, scale, max_prefix, boost_above) for p, q in zip(x, y, strict=True)], dtype="float64")

    return run(a, b)


def jaro_winkler_bound(a: Column, b: Column, scale: float = 0.1, max_prefix: int = 4) -> Column:
    """No less than Jaro-Winkler, natively: every letter that the strings share counts as a match in place."""
    count = lambda s, c: F.length(s) - F.length(F.replace(s, c, F.lit("")))
    common = F.aggregate(F.array_distinct(F.split(a, "")), F.lit(0), lambda t, c: t + F.when(c == "", F.lit(0)).otherwise(F.least(count(a, c), count(b, c))))
    jaro = let(common, lambda m: F.when(m == 0, F.lit(0.0)).otherwise((m / F.length(a) + m / F.length(b) + 1.0) / 3.0))
    bound = let(jaro, lambda j: j + _prefix(a, b, max_prefix) * scale * (1.0 - j))
    return F.when(a == b, F.lit(1.0)).otherwise(bound)


def _prefix(a: Column, b: Column, most: int) -> Column:
    """Letters of the common beginning, `most` of them at most."""
    same = [(F.length(a) >= k) & (F.left(a, F.lit(k)) == F.left(b, F.lit(k))) for k in range(1, most + 1)]
    return F.coalesce(*(F.when(same[k - 1], F.lit(k)) for k in range(most, 0, -1)), F.lit(0))


def letter_mask(s: Column) -> Column:
    """A bit for each letter a-z that is there, one for each that is there twice, and twelve that other letters share."""

    def bit(i: Column) -> Column:
        c = F.substring(s, i, F.lit(1))
        code = F.ascii(c)
        again = F.when(F.position(c, s) < i, F.lit(26)).otherwise(F.lit(0))
        return F.when(code.between(97, 122), code - 97 + again).otherwise(F.lit(52) + F.pmod(code, F.lit(12)))

    places = F.when(F.length(s) > 0, F.sequence(F.lit(1), F.length(s))).otherwise(F.array().cast("array<int>"))
    return F.aggregate(places, F.lit(0).cast("long"), lambda t, i: t.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), bit(i))))


def jaro_winkler_mask_bound(a: Column, b: Column, mask_a: Column, mask_b: Column, scale: float = 0.1, max_prefix: int = 4) -> Column:
    """No less than jaro_winkler_bound, by a few operations on the words' letter masks: each bit that only one of two
    words has is a letter of its own without a match."""
    lone = lambda s, x, y: F.length(s) - F.bit_count(x.bitwiseAND(F.bitwise_not(y)))
    m = F.least(lone(a, mask_a, mask_b), lone(b, mask_b, mask_a))
    jaro = F.when(m <= 0, F.lit(0.0)).otherwise((m / F.length(a) + m / F.length(b) + 1.0) / 3.0)
    return F.when(a == b, F.lit(1.0)).otherwise(jaro + _prefix(a, b, max_prefix) * scale * (1.0 - jaro))


def edit_cost_of(a: str, b: str, insert: float = 1.0, delete: float = 1.0, substitute: float = 1.0, swap: float | None = None) -> float:
    """Least cost of turning a into b; swap exchanges neighbours, if it has a cost."""
    before2: list[float] = []
    before = [j * insert for j in range(len(b) + 1)]
    for i, x in enumerate(a, 1):
        row = [i * delete]
        for j, y in enumerate(b, 1):
            best = min(before[j] + delete, row[j - 1] + insert, before[j - 1] + (0.0 if x == y else substitute))
            if swap is not None and i > 1 and j > 1 and x == b[j - 2] and a[i - 2] == y:
                best = min(best, before2[j - 2] + swap)
            row.append(best)
        before2, before = before, row
    return before[-1]


def weighted_edit_distance(a: Column, b: Column, insert: float = 1.0, delete: float = 1.0, substitute: float = 1.0, swap: float | None = None) -> Column:
    @F.pandas_udf("double")
    def run(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([None if p is None or q is None else edit_cost_of(p, q, insert, delete, substitute, swap) for p, q in zip(x, y, strict=True)], dtype="float64")

    return run(a, b)


def alignment_cost(query: Column, tuple_: Column, c_ins: float = 0.5) -> Column:
    """Least cost of turning the query's words into the tuple's, in order; both array<struct<word, w>>.

    The table's rows are carried as an array: one `aggregate` over the query's words around one over the tuple's."""
    empty = F.array().cast("array<double>")

    def first_row(d: Column) -> Column:
        start = F.array(F.lit(0.0))
        return F.aggregate(d, start, lambda row, x: F.concat(row, F.array(F.element_at(row, -1) + x["w"] * c_ins)))

    def next_row(row: Column, word: Column, d: Column) -> Column:
        def cell(acc: Column, x: Column) -> Column:
            j = F.size(acc)
            replaced = F.get(row, j - 1) + (1.0 - edit_similarity(word["word"], x["word"])) * word["w"]
            best = F.least(F.get(row, j) + word["w"], F.element_at(acc, -1) + x["w"] * c_ins, replaced)
            return F.concat(acc, F.array(best))

        return F.aggregate(d, F.concat(empty, F.array(F.get(row, F.lit(0)) + word["w"])), cell)

    return let(tuple_, lambda d: F.element_at(F.aggregate(query, first_row(d), lambda row, word: next_row(row, word, d)), -1))


def generalised_edit_similarity(query: Column, tuple_: Column, c_ins: float = 0.5) -> Column:
    """1 - least(cost / weight of the query, 1). A query whose words all weigh 0 is similar to equal words only."""
    total = F.aggregate(query, F.lit(0.0), lambda t, x: t + x["w"])
    same = F.transform(query, lambda x: x["word"]) == F.transform(tuple_, lambda x: x["word"])
    ratio = alignment_cost(query, tuple_, c_ins) / F.when(total > 0, total)
    return F.when(total > 0, 1.0 - F.least(ratio, F.lit(1.0))).otherwise(same.cast("double"))


def ges_of(query: list[tuple[str, float]], tuple_: list[tuple[str, float]], c_ins: float = 0.5) -> float:
    """The same in Python: the UDF's twin for long word lists, and the tests' second opinion."""
    total = sum(w for _, w in query)
    if total <= 0:
        return float([x for x, _ in query] == [x for x, _ in tuple_])
    row = [0.0]
    for _, w in tuple_:
        row.append(row[-1] + c_ins * w)
    for x, w in query:
        new = [row[0] + w]
        for j, (y, v) in enumerate(tuple_, 1):
            longest = max(len(x), len(y))
            away = edit_cost_of(x, y) / longest if longest else 0.0
            new.append(min(row[j] + w, new[-1] + c_ins * v, row[j - 1] + away * w))
        row = new
    return 1 - min(row[-1] / total, 1.0)


def ges_udf(query: Column, tuple_: Column, c_ins: float = 0.5) -> Column:
    @F.pandas_udf("double")
    def run(q: pd.Series, d: pd.Series) -> pd.Series:
        return pd.Series([ges_of([(x["word"], x["w"]) for x in a], [(x["word"], x["w"]) for x in b], c_ins) for a, b in zip(q, d, strict=True)], dtype="float64")

    return run(query, tuple_)
