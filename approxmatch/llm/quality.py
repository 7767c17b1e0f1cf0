"""Quality rules with risk-controlled cutoffs, in DataFrame operations only.

Base features of a whole text are row-local array expressions: an 8-word window is a hash, windows are sorted by
hash with their places, equal neighbours are repeated windows, and the words they cover are counted from the sorted
places. No step is more than n log n in the text and nothing is exploded.

Four rules look at ratios of these features; a rule rejects a document whose ratio is above the rule's cutoff for
the document's stratum (its language). Cutoffs come from labelled documents that pass the base rules:

* the grid of cutoffs is fixed beforehand, so that testing it isn't tuned to the labels;
* for a cutoff rejecting k of n good documents, the exact binomial probability of at most k at the rate RISK / rules
  is the p-value of "this cutoff rejects too many good documents";
* every stratum and rule is tested from the loosest cutoff on, as a fixed sequence that ends at the first one not
  significant; the sequences share the error level by Holm's bound for the first step (level / sequences), so that
  with probability 1 - ERROR no certified cutoff anywhere rejects more good documents than allowed;
* among certified cutoffs the one with the best count of bad less `PRICE` times good documents is used, the loosest
  of equals. Without a certified cutoff that helps, the rule is off in the stratum.

Defined cases: a null text has no words and fails the base rules; a null or unseen stratum has no cutoffs beyond the
labels it has; labels without documents and null labels don't count; repeated labels count as often as they
stand, and so do rows that repeat a labelled document, each of which is judged alike; of cutoffs with equal gain the
loosest is used; a text of any length is judged whole; an empty table or no labels give only the base verdict; other
columns aren't read, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import BLANK, WORD, keep, let

WINDOW = 8
RISK = 0.02
ERROR = 0.1
PRICE = 5
SYMBOLS = r"[#*$%&|<>]"
#: Each rule's ratio (of features) and its cutoffs, loosest first; a rule by rule grid, not fitted to data.
GRIDS = {
    "symbols": [0.5, 0.4, 0.3, 0.25, 0.2, 0.16, 0.13, 0.1, 0.08, 0.06, 0.05, 0.04, 0.03, 0.02, 0.015, 0.01],
    "dup_lines": [0.95, 0.9, 0.85, 0.8, 0.75, 0.7, 0.65, 0.6, 0.55, 0.5, 0.45, 0.4, 0.35, 0.3, 0.25, 0.2],
    "repeats": [0.29, 0.28, 0.26, 0.24, 0.22, 0.2, 0.18, 0.16, 0.14, 0.12, 0.1, 0.08, 0.07, 0.06, 0.05, 0.04],
    "word_length": [40.0, 30.0, 25.0, 20.0, 18.0, 16.0, 15.0, 14.0, 13.0, 12.0, 11.0, 10.0, 9.5, 9.0, 8.5, 8.0],
}


def repeated_words(words: Column, window: int = WINDOW) -> Column:
    """Words that stand in windows found twice or more."""
    places = F.sequence(F.lit(1), F.size(words) - window + 1)
    hashed = F.transform(places, lambda i: F.struct(F.xxhash64(F.slice(words, i, window)).alias("h"), i.alias("i")))

    def doubled(s: Column) -> Column:
        same = lambda x, at: F.coalesce(F.get(s, at)["h"] == x["h"], F.lit(False))
        return F.array_sort(F.array_compact(F.transform(s, lambda x, k: F.when(same(x, k - 1) | same(x, k + 1), x["i"]))))

    def covered(p: Column) -> Column:
        return F.aggregate(F.zip_with(p, F.slice(p, 2, F.greatest(F.size(p), F.lit(1))), lambda a, b: F.least(F.lit(window), F.coalesce(b - a, F.lit(window)))), F.lit(0), lambda t, x: t + x)

    n = let(let(F.array_sort(hashed), doubled), covered)
    return F.when(F.size(words) > window, n).otherwise(F.lit(0)).cast("long")


def features(docs: DataFrame) -> DataFrame:
    """doc_id, stratum, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, base_failed."""
    text = F.coalesce("text", F.lit(""))
    lines = F.filter(F.split(text, "\n", -1), lambda x: x.rlike(WORD))
    counted = let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("twice")))
    worded = let(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), lambda w: F.struct(F.size(w).cast("long").alias("n"), repeated_words(w).alias("again")))
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").alias("stratum"), worded.alias("w"),
        F.length(F.regexp_replace(text, BLANK, "")).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.regexp_replace(text, SYMBOLS, ""))).cast("long").alias("n_symbols"), counted.alias("l"),
    )
    rows = rows.select("doc_id", "stratum", F.col("w.n").alias("n_words"), "word_chars", "n_symbols", F.col("l.twice").alias("n_dup_lines"), F.col("w.again").alias("n_repeat_words"), F.col("l.n").alias("n_lines"))
    return rows.withColumn("base_failed", (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words")))


def ratios() -> dict[str, Column]:
    def per(top: str, bottom: str) -> Column:
        return F.col(top) / F.greatest(F.col(bottom), F.lit(1)).cast("double")

    return {"symbols": per("n_symbols", "word_chars"), "dup_lines": per("n_dup_lines", "n_lines"), "repeats": per("n_repeat_words", "n_words"), "word_length": per("word_chars", "n_words")}


def binomial_at_most(k: Column, n: Column, rate: float) -> Column:
    """P(X <= k) of n trials, exactly, from sums of logarithms."""
    n = n.cast("double")
    odds = F.lit(rate / (1 - rate))
    start = n * F.log1p(F.lit(-rate))
    steps = F.when(k > 0, F.sequence(F.lit(1).cast("long"), k)).otherwise(F.array().cast("array<bigint>"))
    total = F.aggregate(
        steps, F.struct(start.alias("lp"), F.exp(start).alias("sum")),
        lambda a, i: let(a["lp"] + F.log((n - i + 1) / i * odds), lambda lp: F.struct(lp.alias("lp"), (a["sum"] + F.exp(lp)).alias("sum"))),
    )["sum"]
    return F.least(total, F.lit(1.0))


def cutoffs(featured: DataFrame, labels: DataFrame, risk: float = RISK, error: float = ERROR, price: float = PRICE) -> DataFrame:
    """stratum, rule, cutoff, good, good_rejected, bad_rejected, p_value of the cutoffs in use."""
    marked = labels.where("doc_id is not null and quality is not null").select(F.col("doc_id").cast("long").alias("doc_id"), (F.col("quality") > 0).alias("fine"))
    known = featured.where("not base_failed").join(marked, "doc_id")
    # The number of cutoffs below the ratio places a document among them: counts, not documents, are sorted.
    places = F.array(*(F.struct(F.lit(rule).alias("rule"), F.size(_below(rule, ratio)).alias("above")) for rule, ratio in ratios().items()))
    counts = known.select("stratum", "fine", F.explode(places).alias("x")).groupBy("stratum", "x.rule", "x.above").agg(F.sum(F.col("fine").cast("long")).alias("good"), F.sum((~F.col("fine")).cast("long")).alias("bad"))
    grid = F.create_map(*(x for rule, g in GRIDS.items() for x in (F.lit(rule), F.array(*map(F.lit, g)))))
    one = counts.groupBy("stratum", "rule").agg(F.sum("good").alias("n"), F.collect_list(F.struct("above", "good", "bad")).alias("all"))  # at most one entry per place of the grid
    one = one.withColumn("sequences", F.count(F.lit(1)).over(Window.partitionBy()))
    each = one.select("stratum", "rule", "n", "all", "sequences", F.posexplode(grid[F.col("rule")]).alias("place", "cutoff"))
    # grids fall: a document is above the cutoff at `place` if at least (length - place) cutoffs are below it
    length = F.size(grid[F.col("rule")])
    over = lambda name: F.aggregate(F.filter("all", lambda x: x["above"] >= length - F.col("place")), F.lit(0).cast("long"), lambda a, x: a + x[name])
    each = each.withColumn("good_rejected", over("good")).withColumn("bad_rejected", over("bad"))
    rate = risk / len(GRIDS)
    p = F.when(F.col("good_rejected") < F.col("n") * rate, binomial_at_most(F.col("good_rejected"), F.col("n"), rate)).otherwise(F.lit(1.0))
    each = keep(each.drop("all").withColumn("p_value", p))
    so_far = Window.partitionBy("stratum", "rule").orderBy("place")
    each = each.withColumn("certified", F.max("p_value").over(so_far) <= F.lit(error) / F.col("sequences"))
    gain = F.col("bad_rejected") - price * F.col("good_rejected")
    best = each.where("certified").withColumn("gain", gain).where("gain > 0").withColumn("turn", F.row_number().over(Window.partitionBy("stratum", "rule").orderBy(F.desc("gain"), "place")))
    return best.where("turn = 1").select("stratum", "rule", "cutoff", F.col("n").alias("good"), "good_rejected", "bad_rejected", "p_value")


def _below(rule: str, ratio: Column) -> Column:
    return F.filter(F.array(*map(F.lit, GRIDS[rule])), lambda c: c < ratio)


def judge(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """doc_id, the base features, base_failed, kept, rejected_by (rules, sorted) of every document."""
    rows = keep(features(docs))
    used = keep(cutoffs(rows, labels, **options).groupBy("stratum").pivot("rule", sorted(GRIDS)).agg(F.first("cutoff")))
    rows = rows.alias("r").join(used.withColumnRenamed("stratum", "of"), F.col("r.stratum").eqNullSafe(F.col("of")), "left")
    rules = [F.when(ratio > F.col(f"`{rule}`"), F.lit(rule)) for rule, ratio in sorted(ratios().items())]
    rows = rows.withColumn("rejected_by", F.array_compact(F.array(*rules)))
    kept = ~F.col("base_failed") & (F.size("rejected_by") == 0)
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept.alias("kept"), "rejected_by")
