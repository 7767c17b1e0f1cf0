"""Mixing sources to target weights, in DataFrame operations only.

1. Targets. Sources in code-point order (null last) weigh 5, 2, 1, repeating, and share all words; none gets more
   than `most` (3) times its own words, and what it leaves is shared by weight among the rest. The level is found
   on the sources' table, sorted by cap / weight: the sources below the level are exactly a prefix of that order.
2. Blocks. A source's documents fall into blocks by a hash of doc_id (64 documents or more in the mean, 1,024
   blocks at most), and each pass over a source goes through its blocks in a new permutation. A source takes as
   many whole passes as fit its target, then whole blocks in permuted order while they fit; from the first block
   that doesn't, documents from the largest down that still fit; then each later block that still fits as a whole;
   then, from all blocks left, documents from the largest down, until none that is left fits.
3. Splitting tree. Every block that a source gives is a unit: the source's quota. The units of all sources are split
   between the two halves of the output shards, then each half again, until one shard is left. A split draws the
   number of units of each source from the multivariate hypergeometric law (source after source, by inversion of the
   exact probabilities within eight standard deviations), so every shard gets its exact size and the quotas of the
   sources add up exactly. A shard takes the next units of each source's permuted sequence: the draws are disjoint.
   There are as many shards, a power of two, as leave UNITS_A_SHARD units to each.
4. Within a shard, order is by a hash of the copy (`position_key`): a local shuffle. What is taken of a document is
   what the shards draw of it.

All randomness is a hash of the seed and of keys, so that reruns and retried tasks agree.

Defined cases: a null text has size 0; a null source is a source of its own, last; documents without words are
never taken; rows that repeat a doc_id are documents of their own, told apart by a hash of the text, and rows equal
in all of these are interchangeable; a text of any length is one document, taken whole or not at all; an empty table
gives an empty result; other columns pass through untouched by `mixed_documents`, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import alone, keep, let, word_count

WEIGHTS = (5.0, 2.0, 1.0)
MOST = 3
BLOCKS = 1024
DOCS_A_BLOCK = 64
UNITS_A_SHARD = 64
SEED = 17


def sized_documents(docs: DataFrame) -> DataFrame:
    """doc_id, source, size, own (a hash of the text): all that the plan needs of a document."""
    return docs.select(F.col("doc_id"), F.col("source"), word_count(F.col("text")).alias("size"), F.xxhash64("text").alias("own"))


def source_targets(sized: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: int = MOST) -> DataFrame:
    """One row per source: source, source_size, n_docs, weight, target."""
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    turn = (F.row_number().over(order) - 1) % len(weights)
    per = per.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), turn + 1))
    cap = F.col("source_size") * F.lit(float(most))
    by_level = Window.orderBy(cap / F.col("weight"), F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    per = (
        per.withColumn("total", F.sum("source_size").over(everything).cast("double"))
        .withColumn("weight_left", F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(by_level), F.lit(0.0)))
        .withColumn("words_left", F.col("total") - F.coalesce(F.sum(cap).over(by_level), F.lit(0.0)))
    )
    # In this order a source is full while the level, given that all before it are full, is above its own cap.
    full = cap / F.col("weight") <= F.col("words_left") / F.col("weight_left")
    per = per.withColumn("full", full)
    level = F.min(F.when(~F.col("full"), F.struct((cap / F.col("weight")).alias("at"), (F.col("words_left") / F.col("weight_left")).alias("level")))).over(everything)
    target = F.when(F.col("full"), cap).otherwise(F.col("weight") * level["level"])
    return per.withColumn("target", F.coalesce(target, cap)).select("source", "source_size", "n_docs", "weight", "target")


def _key(*parts) -> Column:
    return F.xxhash64(F.lit(SEED), *(F.lit(x) if isinstance(x, str | int) else x for x in parts))


def _beside(left: DataFrame, right: DataFrame, on: list[str], how: str = "inner", small: bool = False) -> DataFrame:
    """left with the columns of right, by keys that may be null."""
    right = right.select(*(F.col(c).alias(f"_{c}" if c in on else c) for c in right.columns))
    match = [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in on]
    both = match[0] if len(on) == 1 else match[0] & match[1]
    return left.join(F.broadcast(right) if small else right, both, how).drop(*(f"_{c}" for c in on))


def _largest_first(by_size: DataFrame, keys: list[str]) -> DataFrame:
    """keys, size, m: how many documents of each size go into `room`, from the largest size down; by_size has keys,
    room, size, n."""
    sizes = by_size.groupBy(*keys, "room").agg(F.reverse(F.array_sort(F.collect_list(F.struct("size", "n")))).alias("sizes"))
    step = lambda acc, x: let(
        F.least(x["n"].cast("double"), F.floor((acc["room"] + 0.5) / x["size"]).cast("double")),
        lambda m: F.struct((acc["room"] - m * x["size"]).alias("room"), F.concat(acc["last"], F.when(m > 0, F.array(F.struct(x["size"].alias("size"), m.cast("long").alias("m")))).otherwise(F.array().cast("array<struct<size:bigint,m:bigint>>"))).alias("last")),
    )
    start = F.struct(F.col("room").alias("room"), F.array().cast("array<struct<size:bigint,m:bigint>>").alias("last"))
    return sizes.select(*keys, F.explode(F.aggregate("sizes", start, step)["last"]).alias("x")).select(*keys, "x.size", "x.m")


def plan(sized: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(documents with their block and the number of passes that hold them, units).

    documents: doc_id, source, size, own, source_size, target, block, copies.
    units: source, pass, block, unit (its place in the source's sequence), one row for every block and pass used.
    """
    targets = keep(source_targets(sized))
    small = F.broadcast(targets) if targets.count() <= 100_000 else targets
    placed = sized.join(small, sized["source"].eqNullSafe(targets["source"]), "left").drop(targets["source"])
    n_blocks = F.greatest(F.lit(1), F.least(F.lit(BLOCKS), F.floor(F.col("n_docs") / DOCS_A_BLOCK)))
    placed = placed.withColumn("block", F.pmod(_key("block", F.col("doc_id")), n_blocks).cast("int"))
    passes = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size") + F.lit(1e-9))).otherwise(F.lit(0)).cast("int")
    placed = placed.withColumn("passes", passes)
    blocks = keep(
        placed.groupBy("source", "block").agg(
            F.sum("size").alias("block_size"), F.max("passes").alias("passes"),
            F.max(F.col("target") - F.col("passes") * F.col("source_size")).alias("rest"),
        )
    )
    # The part pass: whole blocks while they fit.
    permuted = Window.partitionBy("source").orderBy(_key("order", F.col("source"), F.col("block"), F.col("passes")), "block")
    running = F.sum("block_size").over(permuted.rowsBetween(Window.unboundedPreceding, 0))
    part = blocks.withColumn("through", running).withColumn("whole", F.col("through") <= F.col("rest") + F.lit(0.5))
    in_order = Window.partitionBy("source", "whole").orderBy("through", _key("order", F.col("source"), F.col("block"), F.col("passes")), "block")
    part = part.withColumn("cut", ~F.col("whole") & (F.row_number().over(in_order) == 1) & (F.col("rest") > 0))
    part = keep(part.withColumn("room", F.when(F.col("cut"), F.col("rest") - F.col("through") + F.col("block_size"))))
    # The cut block: documents of one size are alike; take sizes from the largest down as they fit.
    few = targets.count() <= 100_000
    cuts = part.where("cut").select("source", "block", "room")
    in_cut = _beside(placed, cuts, ["source", "block"], small=few)
    by_size = in_cut.where("size > 0").groupBy("source", "block", "room", "size").agg(F.count(F.lit(1)).alias("n"))
    # At most one entry per distinct size of a block of a bounded share of the source.
    chosen = keep(_largest_first(by_size, ["source", "block"]))
    # Later blocks, at most BLOCKS of a source, that fit as a whole into what the cut block leaves.
    spent = chosen.groupBy("source").agg(F.sum(F.col("size") * F.col("m")).alias("spent"))
    left = _beside(cuts.select("source", "room"), spent, ["source"], "left", few).select("source", (F.col("room") - F.coalesce("spent", F.lit(0))).alias("room"))
    later = _beside(part.where("not whole and not cut and block_size > 0").drop("room"), left, ["source"], small=few)
    key = F.struct("through", _key("order", F.col("source"), F.col("block"), F.col("passes")).alias("key"), "block", "block_size")
    later = later.groupBy("source", "room").agg(F.array_sort(F.collect_list(key)).alias("blocks"))
    fits = lambda acc, x: F.when(
        x["block_size"] <= acc["room"] + 0.5, F.struct((acc["room"] - x["block_size"]).alias("room"), F.concat(acc["got"], F.array(x["block"])).alias("got"))
    ).otherwise(acc)
    later = keep(later.withColumn("end", F.aggregate("blocks", F.struct("room", F.array().cast("array<int>").alias("got")), fits)).select("source", F.col("end.room").alias("room"), F.col("end.got").alias("got")))
    more = later.select("source", F.explode("got").alias("block"), F.lit(True).alias("more"))
    part = _beside(part.drop("room"), more, ["source", "block"], "left", few)
    part = keep(part.withColumn("whole", F.col("whole") | F.coalesce("more", F.lit(False))).drop("more"))
    # Then documents of all blocks left, by the sizes of the source; those of one size in the order of the blocks.
    over = _beside(part.where("not whole and not cut").select("source", "block", "through"), later.select("source", "room"), ["source"], small=few)
    in_rest = _beside(placed, over, ["source", "block"], small=targets.count() <= 1_000).where((F.col("size") > 0) & (F.col("size") <= F.col("room") + 0.5))
    by_block = keep(in_rest.groupBy("source", "block", "through", "room", "size").agg(F.count(F.lit(1)).alias("n")))
    last = _largest_first(by_block.groupBy("source", "room", "size").agg(F.sum("n").alias("n")), ["source"])
    last = _beside(by_block, last.withColumnRenamed("size", "s"), ["source"], small=few).where("size = s")
    before = F.sum("n").over(Window.partitionBy("source", "size").orderBy("through", "block")) - F.col("n")
    last = last.withColumn("m", F.least(F.col("n"), F.col("m") - before)).where("m > 0").select("source", "block", "size", "m")
    chosen = keep(chosen.unionByName(last))
    partly = chosen.select("source", "block").union(cuts.select("source", "block")).distinct().withColumn("partly", F.lit(True))
    part = keep(_beside(part, partly, ["source", "block"], "left", few).withColumn("cut", F.coalesce("partly", F.lit(False))).drop("partly"))
    # Rows equal in doc_id, source, size and text are told apart by their place among each other.
    placed = _beside(placed, part.select("source", "block", "whole", "cut"), ["source", "block"], "left", targets.count() <= 1_000)
    rank = F.row_number().over(Window.partitionBy("source", "block", "size").orderBy(_key("fill", F.col("doc_id")), "doc_id", "own"))
    filled = placed.where("cut").select("source", "block", "size", "doc_id", "own").withColumn("at", rank)
    filled = filled.alias("f").join(
        chosen.alias("c"), F.col("f.source").eqNullSafe(F.col("c.source")) & (F.col("f.block") == F.col("c.block")) & (F.col("f.size") == F.col("c.size")) & (F.col("f.at") <= F.col("c.m")), "left_semi"
    )
    extra = keep(filled.groupBy("doc_id", "source", "size", "own").agg(F.count(F.lit(1)).alias("extra")))
    easy = placed.where(~F.coalesce("cut", F.lit(False))).withColumn("copies", F.col("passes") + F.coalesce("whole", F.lit(False)).cast("int"))
    twin = F.row_number().over(Window.partitionBy("doc_id", "source", "size", "own").orderBy(F.lit(0)))
    hard = placed.where("cut").withColumn("twin", twin)
    hard = hard.alias("p").join(extra.alias("e"), F.col("p.doc_id").eqNullSafe(F.col("e.doc_id")) & F.col("p.source").eqNullSafe(F.col("e.source")) & (F.col("p.size") == F.col("e.size")) & (F.col("p.own") == F.col("e.own")), "left").select("p.*", "extra")
    hard = hard.withColumn("copies", F.col("passes") + (F.col("twin") <= F.coalesce("extra", F.lit(0))).cast("int"))
    columns = ["doc_id", "source", "size", "own", "source_size", "target", "block", "copies"]
    placed = easy.select(columns).unionByName(hard.select(columns))
    placed = placed.withColumn("copies", F.when(F.col("size") > 0, F.col("copies")).otherwise(F.lit(0)))
    used = part.withColumn("turns", F.col("passes") + (F.col("whole") | F.col("cut")).cast("int")).where("turns > 0 and block_size > 0")
    units = used.select("source", "block", F.explode(F.sequence(F.lit(0), F.col("turns") - 1)).alias("pass"))
    place = F.row_number().over(Window.partitionBy("source").orderBy("pass", _key("order", F.col("source"), F.col("block"), F.col("pass")), "block")) - 1
    return placed, units.withColumn("unit", place)


def _hypergeometric(population: Column, good: Column, draws: Column, u: Column) -> Column:
    """Good units among `draws` drawn of `population`, by inversion at u in [0, 1)."""
    some = F.greatest(population, F.lit(1.0))
    mean = draws * good / some
    spread = F.sqrt(F.greatest(mean * (1 - good / some) * (population - draws) / F.greatest(population - 1, F.lit(1.0)), F.lit(0.0))) * 8 + 8
    low = F.greatest(F.lit(0.0), draws + good - population, F.floor(mean - spread)).cast("long")
    high = F.least(good, draws, F.ceil(mean + spread)).cast("long")
    start = F.struct(F.lit(1.0).alias("w"), F.lit(1.0).alias("sum"))

    def ratio(x: Column) -> Column:
        return (good - x) * (draws - x) / ((x + 1) * (population - good - draws + x + 1))

    def draw(lo: Column, hi: Column) -> Column:
        steps = F.when(hi > lo, F.sequence(lo, hi - 1)).otherwise(F.array().cast("array<bigint>"))
        total = F.aggregate(steps, start, lambda a, x: let(a["w"] * ratio(x), lambda w: F.struct(w.alias("w"), (a["sum"] + w).alias("sum"))))["sum"]
        found = let(total * u, lambda goal: F.aggregate(
            steps, F.struct(F.lit(1.0).alias("w"), F.lit(1.0).alias("sum"), lo.alias("at")),
            lambda a, x: let(a["w"] * ratio(x), lambda w: F.struct(w.alias("w"), (a["sum"] + w).alias("sum"), F.when(a["sum"] <= goal, x + 1).otherwise(a["at"]).alias("at"))),
        )["at"])
        return F.when(population > 0, found).otherwise(F.lit(0).cast("long"))

    return let(low, lambda lo: let(high, lambda hi: draw(lo, hi)))


def tree_levels(units: DataFrame) -> int:
    return max(0, (units.count() // UNITS_A_SHARD).bit_length() - 1)


def shard_quotas(units: DataFrame, levels: int) -> DataFrame:
    """shard, source, quota, first: units [first, first + quota) of the source's sequence go to the shard."""
    counts = units.groupBy("source").agg(F.count(F.lit(1)).cast("double").alias("q"))
    node = counts.groupBy().agg(F.array_sort(F.collect_list(F.struct(F.coalesce("source", F.lit("")).alias("key"), F.col("source").isNull().alias("none"), F.col("source").alias("source"), F.col("q")))).alias("s")).select(F.lit(0).alias("node"), F.lit(1 << levels).alias("width"), "s")
    node = keep(node.where(F.size("s") > 0))
    for level in range(levels):
        total = F.aggregate("s", F.lit(0.0), lambda a, x: a + x["q"])
        flip = F.pmod(_key("half", F.lit(level), F.col("node")), F.lit(2)).cast("double")
        node = node.withColumn("total", total).withColumn("left", F.floor((F.col("total") + flip) / 2).cast("double"))
        empty = F.array().cast("array<double>")

        salt = F.lit(level)

        def split(acc: Column, x: Column) -> Column:
            u = F.pmod(_key("draw", salt, F.col("node"), x["key"], x["none"]), F.lit(1 << 40)) / F.lit(float(1 << 40))  # noqa: B023
            return let(_hypergeometric(acc["population"], x["q"], acc["draws"], u).cast("double"), lambda got: F.struct((acc["population"] - x["q"]).alias("population"), (acc["draws"] - got).alias("draws"), F.concat(acc["got"], F.array(got)).alias("got")))

        node = node.withColumn("got", F.aggregate("s", F.struct(F.col("total").alias("population"), F.col("left").alias("draws"), empty.alias("got")), split)["got"])
        half = lambda side: F.zip_with("s", "got", lambda x, g: F.struct(x["key"].alias("key"), x["none"].alias("none"), x["source"].alias("source"), (g if side == 0 else x["q"] - g).alias("q")))
        node = keep(node.select(F.explode(F.array(*(F.struct((F.col("node") * 2 + side).alias("node"), half(side).alias("s")) for side in (0, 1)))).alias("n")).select("n.node", "n.s"))
    flat = node.select(F.col("node").alias("shard"), F.explode("s").alias("x")).select("shard", "x.source", F.col("x.q").cast("long").alias("quota"))
    before = F.sum("quota").over(Window.partitionBy("source").orderBy("shard")) - F.col("quota")
    return flat.withColumn("first", before)


def shard_units(units: DataFrame, levels: int) -> DataFrame:
    """units with their shard."""
    quotas = shard_quotas(units, levels).groupBy("source").agg(F.array_sort(F.collect_list(F.struct("first", "quota", "shard"))).alias("cuts"))
    joined = units.alias("u").join(quotas.alias("q"), F.col("u.source").eqNullSafe(F.col("q.source")), "left").select("u.*", "cuts")
    inside = F.filter("cuts", lambda c: (c["first"] <= F.col("unit")) & (F.col("unit") < c["first"] + c["quota"]))
    return joined.withColumn("shard", inside[0]["shard"]).drop("cuts")


def mix(docs: DataFrame, levels: int | None = None) -> DataFrame:
    """doc_id, source, size, own, source_size, target, copies, taken, shards and position_keys (of the copies that the
    shards draw, in the order of the passes). `levels` halvings give 2 ** levels shards."""
    placed, units = plan(keep(sized_documents(docs)))
    units = keep(units)
    drawn = shard_units(units, tree_levels(units) if levels is None else levels).groupBy("source", "block").agg(F.array_sort(F.collect_list(F.struct("pass", "shard"))).alias("drawn"))
    out = placed.alias("t").join(drawn.alias("s"), F.col("t.source").eqNullSafe(F.col("s.source")) & (F.col("t.block") == F.col("s.block")), "left")
    # A document is in the first `copies` passes of its block; of those, the shards hold the drawn ones.
    own = F.filter(F.coalesce("drawn", F.array().cast("array<struct<pass:int,shard:int>>")), lambda x: x["pass"] < F.col("copies"))
    out = out.select("t.doc_id", "t.source", "size", "own", "source_size", "target", own.alias("drawn"))
    keys = F.transform("drawn", lambda x: _key("shuffle", x["shard"], F.col("doc_id"), F.col("own"), x["pass"]))
    n = F.size("drawn")
    return out.select("doc_id", "source", "size", "own", "source_size", "target", n.alias("copies"), (n * F.col("size")).alias("taken"), F.transform("drawn", lambda x: x["shard"]).alias("shards"), keys.alias("position_keys"))


def mixed_documents(docs: DataFrame, levels: int | None = None, with_shards: bool = False) -> DataFrame:
    """The mix itself: each document once per copy taken, the columns of `docs`, shard by shard and shuffled within
    each; with_shards adds shard and position_key."""
    names = docs.columns
    keys = ["doc_id", "source", "size", "own"]
    places = F.flatten(F.collect_list(F.arrays_zip("shards", "position_keys")))
    copies = alone(lambda: mix(docs, levels).where("copies > 0").groupBy(*keys).agg(F.count(F.lit(1)).alias("twins"), places.alias("places")))
    rows = docs.select(F.struct(*(F.col(f"`{n}`") for n in names)).alias("row"), F.col("doc_id").alias("k"), F.col("source").alias("so"), word_count(F.col("text")).alias("sz"), F.xxhash64("text").alias("ow"))
    # Rows alike in all of these share the copies of their group: the twin-th takes every twins-th.
    rows = rows.join(copies, rows["k"].eqNullSafe(copies["doc_id"]) & rows["so"].eqNullSafe(copies["source"]) & (rows["sz"] == copies["size"]) & (rows["ow"] == copies["own"]))
    single = rows.where("twins = 1").withColumn("twin", F.lit(1))
    several = rows.where("twins > 1").withColumn("twin", F.row_number().over(Window.partitionBy("k", "so", "sz", "ow").orderBy(F.lit(0))))
    rows = single.unionByName(several)
    out = rows.select("row", F.posexplode("places").alias("turn", "place"), "twin", "twins").where(F.col("turn") % F.col("twins") == F.col("twin") - 1)
    out = out.select("row", F.col("place.shards").alias("shard"), F.col("place.position_keys").alias("position_key"))
    out = out.repartitionByRange("shard", "position_key").sortWithinPartitions("shard", "position_key")
    return out.select("row.*", *(["shard", "position_key"] if with_shards else []))
