"""Tokenisation as column expressions: padded q-grams, words, two-level tokens, token bags.

Everything is row-local and native. Whatever a lambda uses more than once is bound by `let`, as Spark evaluates
the body of a higher-order function anew for every element. A null, empty or blank string has no tokens.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

PAD = "$"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with value computed once per row."""
    return F.transform(F.array(value), body)[0]


def normalize(col: Column, case: str = "none", strip_punct: bool = False) -> Column:
    """Trimmed, with whitespace collapsed; case "lower" folds, strip_punct drops what is no letter, digit or blank."""
    if case not in ("none", "lower"):
        raise ValueError(f"unknown case rule {case!r}")
    out = F.lower(col) if case == "lower" else col
    if strip_punct:
        out = F.regexp_replace(out, r"[^\p{L}\p{N}\s]", "")
    return F.trim(F.regexp_replace(out, r"\s+", " "))


_NONE = "array<string>"


def _slide(padded: Column, q: int) -> Column:
    def grams(p: Column) -> Column:
        n = F.length(p) - (q - 1)
        return F.when(n >= 1, F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(p, i, F.lit(q)))).otherwise(F.array().cast(_NONE))

    return let(padded, grams)


def qgrams(col: Column, q: int = 2, pad: str = PAD) -> Column:
    """Grams of the string with q - 1 pads in place of each whitespace run and at both ends."""
    if q < 1:
        raise ValueError("q must be positive")
    pads = pad * (q - 1)
    padded = lambda s: F.concat(F.lit(pads), F.replace(s, F.lit(" "), F.lit(pads)), F.lit(pads))
    return let(F.coalesce(normalize(col), F.lit("")), lambda s: F.when(s == "", F.array().cast(_NONE)).otherwise(_slide(padded(s), q)))


def edit_grams(col: Column, q: int = 2, pad: str = PAD) -> Column:
    """Grams of the string as it stands with q - 1 pads at both ends: length + q - 1 of them, for the edit filter."""
    pads = pad * (q - 1)
    return F.when(F.coalesce(F.length(col), F.lit(0)) == 0, F.array().cast(_NONE)).otherwise(_slide(F.concat(F.lit(pads), col, F.lit(pads)), q))


def words(col: Column) -> Column:
    return let(F.coalesce(normalize(col), F.lit("")), lambda s: F.when(s == "", F.array().cast(_NONE)).otherwise(F.split(s, " ")))


def word_grams(col: Column, q: int = 2) -> Column:
    """array<struct<word, grams>>: words, and the grams of each."""
    return F.transform(words(col), lambda w: F.struct(w.alias("word"), qgrams(w, q).alias("grams")))


def token_bag(tokens: Column) -> Column:
    """array<struct<token, tf>>, by token: runs of the sorted tokens, n log n in their number."""

    def runs(s: Column) -> Column:
        starts = F.filter(F.sequence(F.lit(1), F.size(s)), lambda i: (i == 1) | (F.get(s, i - 1) != F.get(s, i - 2)))
        return let(starts, lambda st: F.zip_with(st, F.slice(st, 2, F.size(st)), lambda a, b: F.struct(F.get(s, a - 1).alias("token"), (F.coalesce(b, F.size(s) + 1) - a).alias("tf"))))

    none = F.array().cast("array<struct<token:string,tf:int>>")
    return let(F.sort_array(tokens), lambda s: F.when(F.size(s) > 0, runs(s)).otherwise(none))


def tokens(col: Column, kind: str = "qgram", q: int = 2, pad: str = PAD, case: str = "none") -> Column:
    """Tokens of either kind; "edit" is the kind of the edit filter."""
    col = F.lower(col) if case == "lower" else col
    if kind == "qgram":
        return qgrams(col, q, pad)
    if kind == "word":
        return words(col)
    if kind == "edit":
        return edit_grams(col, q, pad)
    raise ValueError(f"unknown kind of token {kind!r}")
