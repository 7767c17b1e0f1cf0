"""Erroneous duplicates of clean strings, with ground truth.

All randomness is md5 of (seed, cluster, copy, purpose, place) scaled to [0, 1): the same on any number of partitions,
in a retried task, and in any engine with md5.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text
from ..functions.text import let
from .storage import dealt

#: Fixed: legal forms and what they stand for.
FORMS = (("Inc.", "Incorporated"), ("Corp.", "Corporation"), ("Ltd.", "Limited"), ("Co.", "Company"))


#: Tids of a cluster: its copies are fewer.
COPIES = 1 << 20


@dataclass(frozen=True)
class ErrorSpec:
    """Shares between 0 and 1: of duplicates that are erroneous, of characters hit in one, of neighbouring word pairs
    exchanged in one, of erroneous duplicates whose legal form changes."""

    size: int = 5000
    clean: int = 500
    erroneous: float = 0.5
    extent: float = 0.1
    swap: float = 0.2
    abbreviation: float = 0.5
    duplicates: str = "uniform"


#: Fixed: shares of (erroneous, extent, swap, abbreviation) in percent of the named sets.
PRESETS = {
    "CU1": (90, 30, 20, 50), "CU2": (50, 30, 20, 50), "CU3": (30, 30, 20, 50), "CU4": (10, 30, 20, 50),
    "CU5": (90, 10, 20, 50), "CU6": (50, 10, 20, 50), "CU7": (30, 10, 20, 50), "CU8": (10, 10, 20, 50),
    "F1": (50, 0, 0, 50), "F2": (50, 0, 20, 0), "F3": (50, 10, 0, 0), "F4": (50, 20, 0, 0), "F5": (50, 30, 0, 0),
    "timing": (70, 20, 20, 0),
}
CLASSES = {"dirty": ("CU1", "CU2"), "medium": ("CU3", "CU4", "CU5", "CU6"), "low": ("CU7", "CU8")}


def preset(name: str, size: int = 5000, clean: int = 500, duplicates: str = "uniform") -> ErrorSpec:
    return ErrorSpec(size, clean, *(x / 100 for x in PRESETS[name]), duplicates)


def uniform(seed: int, *parts: Column | str) -> Column:
    """A number in [0, 1) from md5 of seed and parts."""
    key = F.concat_ws("|", F.lit(str(seed)), *(F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 8), 16, 10).cast("double") / float(1 << 32)


def numbered(rows: DataFrame, block: int = 16) -> DataFrame:
    """rows with `place`, from 1, in the order of tid: counted within blocks of 2 ** block tids and over the blocks."""
    rows = rows.withColumn("block", F.shiftright("tid", block))
    blocks = rows.groupBy("block").agg(F.count(F.lit(1)).alias("n"))
    blocks = blocks.select("block", (F.sum("n").over(Window.orderBy("block")) - F.col("n")).alias("before"))
    own = F.row_number().over(Window.partitionBy("block").orderBy("tid"))
    return rows.withColumn("own", own).join(blocks, "block").withColumn("place", (F.col("own") + F.col("before")).cast("int")).drop("own", "block", "before")


def _copies(spec: ErrorSpec, place: Column, u: Column) -> Column:
    """Duplicates of the place-th clean tuple, besides itself."""
    mean = max(spec.size / max(spec.clean, 1) - 1, 0)
    if spec.duplicates == "uniform":
        low = math.floor(mean)
        return F.lit(low) + (u < mean - low).cast("int")
    if spec.duplicates == "zipf":
        total = math.log(spec.clean) + 0.5772156649015329 + 0.5 / spec.clean if spec.clean > 1_000_000 else sum(1 / i for i in range(1, spec.clean + 1))
        return F.round(F.lit(mean * spec.clean / total) / place).cast("int")
    if spec.duplicates == "poisson":
        out, p, below = F.lit(0), math.exp(-mean), 0.0
        for k in range(int(mean + 10 * math.sqrt(mean + 1)) + 1):
            below += p
            out = out + (u >= min(below, 1.0)).cast("int")
            p *= mean / (k + 1)
        return out
    raise ValueError(f"unknown distribution {spec.duplicates!r}")


def swap_words(s: Column, share: float, seed: int, *key: Column) -> Column:
    """Disjoint pairs of neighbouring words exchanged, each with probability `share`."""

    def body(ws: Column) -> Column:
        def word(i: Column) -> Column:  # i from 0: the partner stands beside it in its pair
            first = i - i % 2
            whole = first + 1 < F.size(ws)
            hit = whole & (uniform(seed, *key, "swap", first) < share)
            return F.get(ws, F.when(hit, first + (1 - i % 2)).otherwise(i))

        return F.array_join(F.transform(F.sequence(F.lit(0), F.size(ws) - 1), word), " ")

    return F.when(F.size(text.words(s)) > 1, let(text.words(s), body)).otherwise(s) if share > 0 else s


def change_form(s: Column) -> Column:
    """The short form of a legal form for the long one, and the other way round, at the end of the string."""
    out = s
    for short, long in reversed(FORMS):
        out = F.when(s.endswith(" " + short), F.concat(F.substring(s, F.lit(1), F.length(s) - len(short)), F.lit(long))).when(
            s.endswith(" " + long), F.concat(F.substring(s, F.lit(1), F.length(s) - len(long)), F.lit(short))
        ).otherwise(out)
    return out


def edit_characters(s: Column, extent: float, seed: int, *key: Column) -> Column:
    """round(extent * length) different places hit, those with the least numbers; each is an insertion, deletion,
    replacement or exchange with the next character, evenly."""
    if extent <= 0:
        return s

    def hits(n: Column) -> Column:
        drawn = F.array_sort(F.transform(F.sequence(F.lit(1), n), lambda i: F.struct(uniform(seed, *key, "place", i).alias("u"), i.alias("i"))))
        count = F.round(n * extent).cast("int")
        return F.array_sort(F.transform(F.slice(drawn, F.lit(1), count), lambda x: x["i"]))

    def apply(places: Column) -> Column:
        # from the last place to the first, so that earlier places keep their number
        def step(acc: Column, i: Column) -> Column:
            letter = F.chr((F.floor(uniform(seed, *key, "letter", i) * 26) + 97).cast("int"))
            kind = F.floor(uniform(seed, *key, "kind", i) * 4).cast("int")
            head, here = F.substring(acc, F.lit(1), i - 1), F.substring(acc, i, F.lit(1))
            after, tail = F.substring(acc, i + 1, F.lit(1)), F.substring(acc, i + 1, F.length(acc))
            beyond = F.substring(acc, i + 2, F.length(acc))
            return F.when(kind == 0, F.concat(head, letter, here, tail)).when(kind == 1, F.concat(head, tail)).when(kind == 2, F.concat(head, letter, tail)).otherwise(F.concat(head, after, here, beyond))

        return F.aggregate(F.reverse(places), s, step)

    return F.when(F.coalesce(F.length(s), F.lit(0)) > 0, let(let(F.length(s), hits), apply)).otherwise(s)


def generate_dirty(clean: DataFrame, spec: ErrorSpec, seed: int = 42) -> DataFrame:
    """tid, cluster_id, s, is_clean, is_erroneous from clean (tid, s): its first spec.clean tuples by tid (all, if they
    aren't more), each with its duplicates. tid is cluster_id * COPIES + copy."""
    first = numbered(clean.orderBy("tid").limit(spec.clean)).select(F.col("tid").alias("cluster_id"), "s", "place")
    n = _copies(spec, F.col("place"), uniform(seed, F.col("cluster_id"), "count"))
    rows = dealt(first, "cluster_id").withColumn("copy", F.explode(F.sequence(F.lit(0), n)))
    key = (F.col("cluster_id"), F.col("copy"))
    wrong = (F.col("copy") > 0) & (uniform(seed, *key, "wrong") < spec.erroneous)
    rows = rows.withColumn("is_clean", F.col("copy") == 0).withColumn("is_erroneous", wrong)
    form = F.when(uniform(seed, *key, "form") < spec.abbreviation, change_form(F.col("s"))).otherwise(F.col("s")) if spec.abbreviation > 0 else F.col("s")
    # each step in its own column: the next one uses it several times
    rows = rows.withColumn("s1", F.when(F.col("is_erroneous"), form).otherwise(F.col("s")))
    rows = rows.withColumn("s2", F.when(F.col("is_erroneous"), swap_words(F.col("s1"), spec.swap, seed, *key)).otherwise(F.col("s1")))
    rows = rows.withColumn("s3", F.when(F.col("is_erroneous"), edit_characters(F.col("s2"), spec.extent, seed, *key)).otherwise(F.col("s2")))
    return rows.select((F.col("cluster_id") * COPIES + F.col("copy")).alias("tid"), "cluster_id", F.col("s3").alias("s"), "is_clean", "is_erroneous")


def truth(dirty: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, tid of the tuples in the cluster of each query (qid is a tid of the set)."""
    own = dirty.select(F.col("tid").alias("qid"), "cluster_id").join(queries.select("qid"), "qid")
    return own.join(dirty.select("tid", "cluster_id"), "cluster_id").select("qid", "tid")
