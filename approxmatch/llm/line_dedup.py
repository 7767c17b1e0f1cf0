"""Repeated line runs, by a suffix array over line ids, in DataFrame operations only.

1. Lines with a word get an id; a document is the sequence of its ids. Lines are told apart by 128 bits: an id is a
   64-bit hash, or a hash of both of a line's hashes where two repeated lines share the first. Only ids that stand at
   least twice in the corpus can be part of a repeated run: the others end the sequences ("stretches") that go on.
2. Prefix doubling. A suffix is named by the pair (id of its first line, place among the suffixes with that line).
   In a round the name at the offset 1, 2, 4, ... in the same stretch orders the suffixes of each name, and a
   suffix moves up by the number of those before it. The order inside a name needs counts of *different* next names
   only, which are aggregated before anything is sorted, in three steps (the next id's highest byte, the next id with
   the block of its name, the name), so that a line with many continuations isn't sorted in one task. Rounds stop when
   a prefix of `depth` lines is sorted, without one when no name has two next names.
3. LCP intervals. The suffixes with a common prefix of k lines are an interval of the array: the occurrences of one
   run. Of two names that are sorted to 2^r lines, one at the run's start and one that ends where it ends, the
   interval is known for any k from 2^r to 2^(r + 1). Its first occurrence by document and line is the original, the
   others are later copies.
4. A line goes if it lies in a later copy of a run that holds at least `least_words` words. Any such line also lies
   in a copied window of at most `least_words` lines, as every line has a word: intervals of up to `least_words`
   lines decide, and `deduplicated` sorts to that depth. `maximal_runs` sorts to the end and reports the whole runs.

Order is by doc_id (null first), then by a hash of the text. Rows equal in both are one document and keep the same
lines. Lines without a word are never deleted and don't part runs.

Defined cases: a null text stays null; an empty text stays empty; a document may lose all its lines and then has
the text ""; long documents are sequences of rows, not arrays, until their kept lines are joined; an empty table
gives an empty result; other columns pass through, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import WORD, alone, keep, let

LEAST_WORDS = 5
#: A key with more than this share of all rows is hot: at most 1 / HOT of them, which are broadcast.
HOT = 1e-4
_FIRST = -(1 << 63)
_AT = ("d", "t", "i")


def _key(docs: DataFrame) -> list[Column]:
    return [F.coalesce(F.col("doc_id").cast("long"), F.lit(_FIRST)).alias("d"), F.xxhash64("text").alias("t")]


def line_table(docs: DataFrame) -> DataFrame:
    """d, t (the document), p (line number), i (number among lines with a word), h, g (hashes), w (words)."""
    lines = F.transform(F.split("text", "\n", -1), lambda x, p: F.struct(p.alias("p"), F.xxhash64(x).alias("h"), F.xxhash64(F.lit("line"), x).alias("g"), F.size(F.regexp_extract_all(x, F.lit(WORD), F.lit(0))).alias("w")))
    rows = docs.where("text is not null").select(*_key(docs), F.posexplode(F.filter(lines, lambda x: x["w"] > 0)).alias("i", "x"))
    return rows.select("d", "t", "i", "x.p", "x.h", "x.g", "x.w")


def _with_hot(rows: DataFrame, table: DataFrame, on: list[str], total: int) -> DataFrame:
    """rows joined to table (on, n, ...; n counts the rows of a key): hot keys by broadcast, the others by hash."""
    limit = max(total * HOT, 1)
    hot = keep(table.where(F.col("n") > limit))
    rest = rows.join(F.broadcast(hot.select(*on)), on, "left_anti").join(table.where(F.col("n") <= limit), on)
    return rows.join(F.broadcast(hot), on).unionByName(rest)


def repeated_lines(lines: DataFrame) -> DataFrame:
    """The lines that stand twice, with h as their id and their stretch s (the same along consecutive lines)."""
    often = keep(lines.groupBy("h", "g").agg(F.count(F.lit(1)).alias("n")).where("n > 1"))
    clash = often.groupBy("h").agg(F.count(F.lit(1)).alias("kinds")).where("kinds > 1")
    often = often.join(clash, "h", "left").select("h", "g", "n", F.when(F.col("kinds").isNull(), F.col("h")).otherwise(F.xxhash64("h", "g")).alias("id"))
    total = often.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    along = Window.partitionBy("d", "t").orderBy("i")
    rows = _with_hot(lines, often, ["h", "g"], total).select("d", "t", "i", "p", F.col("id").alias("h"), "w")
    rows = rows.withColumn("s", F.col("i") - F.dense_rank().over(along)).withColumn("twin", F.lag("i").over(along))
    return rows.where("twin is null or twin <> i").drop("twin")  # rows that repeat a document add nothing


def _places(kinds: DataFrame) -> DataFrame:
    """kinds (h, name, nh, nn, n) with `up`: how many suffixes of the name stand before, by nh and nn (nulls first)."""
    kinds = kinds.withColumn("top", F.coalesce(F.shiftright("nh", 56).cast("int"), F.lit(-129))).withColumn("block", F.coalesce(F.shiftright("nn", 16), F.lit(-1)))
    blocks = keep(kinds.groupBy("h", "name", "top", "nh", "block").agg(F.sum("n").alias("n")))
    tops = blocks.groupBy("h", "name", "top").agg(F.sum("n").alias("n"))
    before = lambda keys, *order: F.sum("n").over(Window.partitionBy(*keys).orderBy(*order)) - F.col("n")
    tops = tops.select("h", "name", "top", before(["h", "name"], "top").alias("up1"))
    blocks = blocks.withColumn("up2", before(["h", "name", "top"], F.col("nh").asc_nulls_first(), "block"))
    blocks = blocks.join(tops, ["h", "name", "top"]).select("h", "name", F.col("nh").alias("bh"), "block", (F.col("up1") + F.col("up2")).alias("base"))
    own = kinds.withColumn("own", before(["h", "name", "nh", "block"], F.col("nn").asc_nulls_first()))
    return own.alias("k").join(blocks.alias("b"), (F.col("k.h") == F.col("b.h")) & (F.col("k.name") == F.col("b.name")) & F.col("k.nh").eqNullSafe(F.col("bh")) & (F.col("k.block") == F.col("b.block"))).select("k.h", "k.name", "nh", "nn", (F.col("base") + F.col("own")).alias("up"))


def suffix_names(lines: DataFrame, depth: int | None = None) -> list[DataFrame]:
    """lines with `name`, for the depths 1, 2, 4, ... up to the largest power of two within `depth` (without one: until
    no name splits): suffixes of one first line h in the order of name, equal names equal to the depth."""
    along = Window.partitionBy("d", "t", "s").orderBy("i")
    rows, offset = lines.withColumn("name", F.lit(0).cast("long")), 1
    out = [rows]
    while depth is None or offset * 2 <= depth:
        rows = keep(rows.withColumn("nh", F.lead("h", offset).over(along)).withColumn("nn", F.lead("name", offset).over(along)))
        kinds = rows.groupBy("h", "name", "nh", "nn").agg(F.count(F.lit(1)).alias("n"))
        # A name with one continuation stays as it is: only the others are placed.
        many = kinds.groupBy("h", "name").agg(F.count(F.lit(1)).alias("kinds")).where("kinds > 1").select("h", "name")
        up = keep(_places(keep(kinds.join(many, ["h", "name"], "left_semi"))).where("up > 0"))
        if up.isEmpty():
            if depth is None:
                return out
            rows = rows.drop("nh", "nn")
        else:
            # What stays in its place needs no partner; an end of a stretch is the least and stays always.
            up = up.select(F.col("h").alias("h2"), F.col("name").alias("name2"), F.col("nh").alias("nh2"), F.col("nn").alias("nn2"), "up")
            rows = rows.join(up, (F.col("h") == F.col("h2")) & (F.col("name") == F.col("name2")) & (F.col("nh") == F.col("nh2")) & (F.col("nn") == F.col("nn2")), "left")
            rows = keep(rows.withColumn("name", F.col("name") + F.coalesce("up", F.lit(0))).drop("nh", "nn", "h2", "name2", "nh2", "nn2", "up"))
        out.append(rows)
        offset *= 2
    return out


def lcp_intervals(levels: list[DataFrame], depth: int) -> DataFrame:
    """d, t, i, k: the windows of k lines, 1 to depth, that aren't the first of their interval."""
    names = [x.select(*_AT, F.col("name").alias(f"n{r}")) for r, x in enumerate(levels)]
    rows = levels[0].drop("name")
    for x in names:
        rows = rows.join(x, list(_AT))
    along = Window.partitionBy("d", "t", "s").orderBy("i")
    windows = []
    for k in range(1, depth + 1):
        r = min(k.bit_length() - 1, len(levels) - 1)
        back = k - (1 << r)  # the second name ends where the window ends
        last = F.lead("h", k - 1).over(along)
        windows.append(F.when(last.isNotNull(), F.struct(F.lit(k).alias("k"), F.col("h").alias("a"), F.col(f"n{r}").alias("b"), F.lead("h", back).over(along).alias("c"), F.lead(f"n{r}", back).over(along).alias("e"))))
    rows = rows.select(*_AT, *(w.alias(f"w{k}") for k, w in enumerate(windows)))
    each = rows.select(*_AT, F.explode(F.array_compact(F.array(*(f"w{k}" for k in range(depth))))).alias("x"))
    each = keep(each.select(*_AT, "x.*"))
    key = ["k", "a", "b", "c", "e"]
    groups = keep(each.groupBy(*key).agg(F.min(F.struct(*_AT)).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1"))
    total = groups.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    return _with_hot(each, groups, key, total).where(F.col("first") < F.struct(*_AT)).select(*_AT, "k")


def later_copies(docs: DataFrame, least_words: int = LEAST_WORDS) -> DataFrame:
    """d, t, p, w: the lines that go."""
    lines = alone(lambda: repeated_lines(keep(line_table(docs))))
    copied = lcp_intervals(suffix_names(lines, least_words), least_words).groupBy(*_AT).agg(F.collect_set("k").alias("ks"))
    along = Window.partitionBy("d", "t", "s").orderBy("i")
    longest, total = F.lit(0), F.lit(0)
    for k in range(1, least_words + 1):  # the longest copied window from here that holds enough words
        total = total + F.lead("w", k - 1).over(along)
        longest = F.when(F.coalesce(F.array_contains("ks", k) & (total >= least_words), F.lit(False)), F.lit(k)).otherwise(longest)
    rows = lines.join(copied, list(_AT), "left").withColumn("reach", F.col("i") + longest)
    covered = F.max("reach").over(along.rowsBetween(Window.unboundedPreceding, 0)) > F.col("i")
    return rows.withColumn("gone", covered).where("gone").select("d", "t", "p", "w")


def neighbour_prefixes(levels: list[DataFrame], classes: DataFrame) -> DataFrame:
    """h, name, next_name, lcp: the longest common prefix (in lines) of neighbours in the suffix array. A name is the
    number of suffixes before it, so the next one is name + n. From the largest depth down, equal names of what
    follows the prefix so far lengthen it."""
    after = classes.select("h", F.col("name").alias("next_name"), F.col("at").alias("next_at"))
    pairs = classes.withColumn("next_name", F.col("name") + F.col("n")).join(after, ["h", "next_name"])
    pairs = keep(pairs.select("h", "name", "next_name", "at", "next_at", F.lit(0).alias("lcp")))
    for r in range(len(levels) - 2, -1, -1):  # different suffixes differ within the last depth
        rows = pairs
        for side in ("at", "next_at"):
            names = levels[r].select(F.col("d").alias("fd"), F.col("t").alias("ft"), F.col("i").alias("fi"), F.struct("h", "name").alias(f"{side}_name"))
            on = (F.col(f"{side}.d") == F.col("fd")) & (F.col(f"{side}.t") == F.col("ft")) & (F.col(f"{side}.i") + F.col("lcp") == F.col("fi"))
            # Beyond a stretch's end there may be another one: only its own lines count.
            rows = rows.join(names, on, "left").withColumn(f"{side}_name", F.when(F.col("lcp") < F.col(f"{side}.rest"), F.col(f"{side}_name"))).drop("fd", "ft", "fi")
        same = F.coalesce(F.col("at_name") == F.col("next_at_name"), F.lit(False))
        pairs = keep(rows.withColumn("lcp", F.col("lcp") + F.when(same, F.lit(1 << r)).otherwise(F.lit(0))).drop("at_name", "next_at_name"))
    return pairs


def maximal_runs(docs: DataFrame) -> DataFrame:
    """doc_id, line, lines, other_doc, other_line: the runs of lines (with a word) that stand at least twice, as long as
    they go and each where it begins, with another place of the run. Line numbers count all lines from 0, `lines` those
    with a word. Rows that repeat a document count once; a null doc_id stays null.

    The longest run from a suffix is its longest common prefix with a neighbour in the suffix array: all of it, where
    another suffix has its name."""
    lines = alone(lambda: repeated_lines(keep(line_table(docs))))
    levels = suffix_names(lines)
    rest = F.count(F.lit(1)).over(Window.partitionBy("d", "t", "s").orderBy(F.desc("i"))).cast("int")
    place = F.struct("d", "t", "i", "p", "rest")
    rows = keep(levels[-1].withColumn("rest", rest).withColumn("at", place))
    classes = keep(rows.groupBy("h", "name").agg(F.count(F.lit(1)).alias("n"), F.min("at").alias("at"), F.max("at").alias("last")))
    pairs = neighbour_prefixes(levels, classes.select("h", "name", "n", "at"))
    sides = pairs.select("h", "name", "lcp", F.col("next_at").alias("other")).unionByName(pairs.select("h", F.col("next_name").alias("name"), "lcp", F.col("at").alias("other")))
    best = sides.groupBy("h", "name").agg(F.max("lcp").alias("lcp"), F.max_by("other", F.struct("lcp", "other")).alias("other"))
    known = keep(classes.join(best, ["h", "name"], "left").select("h", "name", "n", F.col("at").alias("first"), "last", F.coalesce("lcp", F.lit(0)).alias("lcp"), "other"))
    rows = _with_hot(rows.select("h", "name", "s", "at"), known, ["h", "name"], lines.count())
    twice = F.col("n") > 1
    rows = rows.select(
        "s", "at.*", F.when(twice, F.col("at.rest")).otherwise(F.col("lcp")).alias("k"),
        F.when(twice, F.when(F.col("first") == F.col("at"), F.col("last")).otherwise(F.col("first"))).otherwise(F.col("other")).alias("other"),
    )
    longer = F.coalesce(F.lag("k").over(Window.partitionBy("d", "t", "s").orderBy("i")) > F.col("k"), F.lit(False))
    starts = rows.withColumn("inside", longer).where("k > 0 and not inside")
    named = lambda c: F.when(c != _FIRST, c)
    return starts.select(named(F.col("d")).alias("doc_id"), F.col("p").alias("line"), F.col("k").alias("lines"), named(F.col("other.d")).alias("other_doc"), F.col("other.p").alias("other_line"))


def deduplicated(docs: DataFrame, least_words: int = LEAST_WORDS, with_counts: bool = False, drop_emptied: bool = False) -> DataFrame:
    """docs without the later copies: the columns of docs, with text (and n_chars, if it is there) anew.
    with_counts adds lines_deleted and words_deleted; drop_emptied drops the documents that lose every line with a
    word (not those that had none)."""
    names = docs.columns
    gone = alone(lambda: later_copies(docs, least_words)).distinct().groupBy("d", "t").agg(F.array_sort(F.collect_list("p")).alias("gone"), F.sum("w").alias("words_deleted"))
    d, t = _key(docs)
    rows = docs.select(F.struct(*(F.col(f"`{n}`") for n in names)).alias("row"), d, t).join(gone, ["d", "t"], "left")

    def without(lines: Column) -> Column:
        # The lines between two deleted ones are a slice: linear in the text, however many go.
        starts = F.concat(F.array(F.lit(-1)), F.col("gone"))
        ends = F.concat(F.col("gone"), F.array(F.size(lines)))
        return F.array_join(F.flatten(F.zip_with(starts, ends, lambda s, e: F.slice(lines, s + 2, e - s - 1))), "\n")

    text = F.when(F.col("gone").isNull(), F.col("row.text")).otherwise(let(F.split("row.text", "\n", -1), without))
    rows = rows.withColumn("new_text", text)
    if drop_emptied:
        rows = rows.where(F.col("gone").isNull() | F.col("new_text").rlike(WORD))
    columns = [F.col("new_text").alias(n) if n == "text" else F.coalesce(F.length("new_text").cast("long"), F.col("row.n_chars")).alias(n) if n == "n_chars" else F.col(f"row.`{n}`").alias(n) for n in names]
    counts = [F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("lines_deleted"), F.coalesce("words_deleted", F.lit(0)).cast("long").alias("words_deleted")] if with_counts else []
    return rows.select(*columns, *counts)
