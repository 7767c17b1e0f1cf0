"""Token weights as column expressions. Counts are cast to double first: SQL decimals would round the ratios."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TINY = 1e-12


def real(x: Column | float | int) -> Column:
    return (x if isinstance(x, Column) else F.lit(x)).cast("double")


def idf(n: Column | float, df: Column) -> Column:
    return F.log(real(n)) - F.log(real(df))


def rs_weight(n: Column | float, df: Column, floor: float | None = None) -> Column:
    """Log odds of a token outside the tuples that hold it; negative for tokens of more than half of all tuples."""
    n, df = real(n), real(df)
    out = F.log((n - df + 0.5) / (df + 0.5))
    return out if floor is None else F.greatest(out, F.lit(float(floor)))


def bm25_doc_weight(rs: Column, tf: Column, dl: Column, avgdl: Column | float, k1: float = 1.5, b: float = 0.675) -> Column:
    length = (1.0 - b) + real(dl) * b / real(avgdl)
    return rs * real(tf) * (k1 + 1.0) / (length * k1 + real(tf))


def bm25_query_weight(tf: Column, k3: float = 8.0) -> Column:
    return real(tf) * (k3 + 1.0) / (real(tf) + k3)


def p_ml(tf: Column, dl: Column) -> Column:
    return real(tf) / real(dl)


def p_avg(sum_pml: Column, df: Column) -> Column:
    return sum_pml / real(df)


def lm_risk(p_average: Column, tf: Column, dl: Column) -> Column:
    """Geometric risk of the mean probability at the count tf."""
    mean = p_average * real(dl)
    return F.pow(mean / (mean + 1.0), real(tf)) / (mean + 1.0)


def lm_prob(tf: Column, dl: Column, sum_pml: Column, df: Column) -> Column:
    """Probability of a token in a tuple that holds it, clamped inside (0, 1)."""
    average = p_avg(sum_pml, df)
    risk = lm_risk(average, tf, dl)
    p = F.pow(p_ml(tf, dl), 1.0 - risk) * F.pow(average, risk)
    return F.least(F.greatest(p, F.lit(TINY)), F.lit(1.0 - TINY))


def background(cf: Column, cs: Column | float) -> Column:
    """Share of a token among all tokens, clamped below 1."""
    return F.least(real(cf) / real(cs), F.lit(1.0 - TINY))


def hmm_weight(tf: Column, dl: Column, cf: Column, cs: Column | float, a0: float = 0.2) -> Column:
    return p_ml(tf, dl) * (1.0 - a0) / (real(cf) / real(cs) * a0) + 1.0
