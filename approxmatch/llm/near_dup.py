"""Near-duplicate documents: fast similarity sketches, banding, and verification on the full sets.

Sets. A document's set holds the 64-bit hashes of its different shingles of five words (A-Z lower-cased); with fewer
words, one hash of all of them; with none it is empty and linked with nothing. Documents with one set (compared by
two further 64-bit sums over it) are one class: copies are never expanded into pairs.

Sketch. 128 bins are filled in rounds. In round i < 128 every element goes to one hashed bin with a hashed value;
in round 128 + j every element goes to bin j. A bin keeps the least (round, value); rounds stop when all bins are
full, so every coordinate is filled, and later rounds could not change one. Large sets need two or three rounds.

Candidates. 32 bands of 4 coordinates: classes at the similarity of 0.75 share a band with probability
1 - (1 - 0.75^4)^32 > 0.999994. Each class is first compared with one centre (the class that stands in the largest
bands), then with the centre of each band whose component differs, there only if at least half of the 128
coordinates agree (at the similarity of 0.75 that is missed with probability below 1e-9). A class that is then in
another component than most of some band (a stray) meets the other classes of undecided bands by the exact prefix
and position filters over rare elements (`prefix_pairs`). Pairs inside a component need no comparison, and a
group's members are never all paired.

Links. A pair counts if 100 * intersection >= 75 * union on the full sets. Components come from alternating
large-star and small-star rounds on tables, with nothing collected.

Defined cases: a null or empty text has an empty set and is kept; rows that share a doc_id are one document, and their
classes are linked; a row without doc_id keeps its size, has no component and is kept; of equal texts the smallest
doc_id stays; texts of any length; an empty table gives an empty result; other columns aren't read, and `deduplicated`
passes them on, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import U, alone, chunks, keep, lowered, mix, seeds, span_hashes, word_spans

SHINGLE = 5
BINS = 128
ROWS_A_BAND = 4
BANDS = BINS // ROWS_A_BAND
PERCENT = 75
LEAST_AGREEMENT = BINS // 2

_WORD_PLACE = seeds(SHINGLE, 11) | U(1)
_SHORT = seeds(SHINGLE + 1, 29)
_ROUND = seeds(2 * BINS, 101)
_SUMS = seeds(2, 7)
_ROW = seeds(ROWS_A_BAND, 53) | U(1)
_BAND = seeds(BANDS, 71)
_EMPTY = ~U(0)
_BIN_SHIFT = U(64 - (BINS - 1).bit_length())


def shingle_sets(data: np.ndarray, at: np.ndarray, shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, rows): the set of each row of a chunk, sorted by row and hash."""
    data = lowered(data)
    starts, ends, row = word_spans(data, at)
    words = span_hashes(data, starts, ends)
    count = np.bincount(row, minlength=len(at) - 1)
    first = np.cumsum(count) - count
    if len(words) >= shingle:
        full = np.zeros(len(words) - shingle + 1, U)
        for j in range(shingle):
            full += words[j : len(words) - shingle + 1 + j] * _WORD_PLACE[j]
        whole = row[: len(full)] == row[shingle - 1 :]
        hashes, rows = [mix(full[whole])], [row[: len(full)][whole]]
    else:
        hashes, rows = [], []
    for n in range(1, shingle):  # all words of a short text as one
        some = np.flatnonzero(count == n)
        if len(some):
            total = np.zeros(len(some), U)
            for j in range(n):
                total += words[first[some] + j] * _WORD_PLACE[j]
            hashes.append(mix(total + _SHORT[n]))
            rows.append(some)
    if not hashes:
        return np.zeros(0, U), np.zeros(0, np.int64)
    h, r = np.concatenate(hashes), np.concatenate(rows)
    order = np.lexsort((h, r))
    h, r = h[order], r[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (r[1:] != r[:-1])
    return h[new], r[new]


def sketches(h: np.ndarray, r: np.ndarray, n: int) -> np.ndarray:
    """The (n, BINS) sketch of each row's set; rows without elements stay unfilled."""
    out = np.full((n, BINS), _EMPTY, U)
    flat = out.reshape(-1)
    rounds = U(56)
    low = (U(1) << rounds) - U(1)
    active = np.zeros(n, bool)
    active[r] = True
    for i in range(2 * BINS):
        if not len(h):
            break
        x = mix(h ^ _ROUND[i])
        value = (U(i) << rounds) | (x & low)
        if i < BINS:
            np.minimum.at(flat, r * BINS + (x >> _BIN_SHIFT).astype(np.int64), value)
        else:
            np.minimum.at(flat, r * BINS + (i - BINS), value)
        which = np.flatnonzero(active)
        done = which[(out[which] != _EMPTY).all(1)]
        if len(done):
            active[done] = False
            go = active[r]
            h, r = h[go], r[go]
    return out


def band_keys(sketch: np.ndarray) -> np.ndarray:
    """The (n, BANDS) keys; equal only in the same band."""
    cells = sketch.reshape(len(sketch), BANDS, ROWS_A_BAND)
    total = np.zeros(cells.shape[:2], U)
    for j in range(ROWS_A_BAND):
        total += mix(cells[:, :, j]) * _ROW[j]
    return mix(total ^ _BAND)


def signatures(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, f1, f2 (the class), bands, marks (a byte of each coordinate)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for start, end, data, at in chunks(b[1]):
                n = end - start
                with np.errstate(over="ignore"):
                    h, r = shingle_sets(data, at)
                    sketch = sketches(h, r, n)
                    size = np.bincount(r, minlength=n)
                    sums = []
                    for s in _SUMS:
                        total = np.zeros(len(h) + 1, U)
                        np.cumsum(mix(h ^ s), out=total[1:])
                        edge = np.concatenate([[0], np.cumsum(size)])
                        sums.append((total[edge[1:]] - total[edge[:-1]]).view(np.int64))
                    keys = band_keys(sketch).view(np.int64)
                    marks = (mix(sketch) & U(255)).astype(np.uint8)
                yield pa.RecordBatch.from_arrays(
                    [
                        b[0].slice(start, n), pa.array(size, pa.int64()), pa.array(sums[0]), pa.array(sums[1]),
                        pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * BANDS), pa.array(keys.ravel())),
                        pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(np.arange(n + 1, dtype=np.int32) * BINS), pa.py_buffer(marks.tobytes())]),
                    ],
                    ["doc_id", "n_shingles", "f1", "f2", "bands", "marks"],
                )

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n_shingles long, f1 long, f2 long, bands array<long>, marks binary")


def full_sets(docs: DataFrame) -> DataFrame:
    """doc_id, hashes: the set of each document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for start, end, data, at in chunks(b[1]):
                with np.errstate(over="ignore"):
                    h, r = shingle_sets(data, at)
                edge = np.concatenate([[0], np.cumsum(np.bincount(r, minlength=end - start))]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b[0].slice(start, end - start), pa.ListArray.from_arrays(pa.array(edge), pa.array(h.view(np.int64)))], ["doc_id", "hashes"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, hashes array<long>")


def agreement(pairs: DataFrame, least: int = LEAST_AGREEMENT) -> DataFrame:
    """Pairs (a, b, marks_a, marks_b) of which at least `least` coordinates agree: a, b."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if n:
                x, y = (np.frombuffer(b"".join(batch[k].to_pylist()), np.uint8).reshape(n, BINS) for k in (2, 3))
                good = pa.array((x == y).sum(1) >= least)
                yield pa.RecordBatch.from_arrays([batch[0].filter(good), batch[1].filter(good)], ["a", "b"])

    return pairs.select("a", "b", "marks_a", "marks_b").mapInArrow(run, "a long, b long")


def may_reach(x: Column, y: Column, percent: int = PERCENT) -> Column:
    """Sizes between which the similarity is possible."""
    return F.least(x, y) * 100 >= F.greatest(x, y) * percent


def verified(pairs: DataFrame, sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The pairs (a, b) whose full sets reach the similarity."""
    left = pairs.join(sets.select(F.col("doc_id").alias("a"), F.col("hashes").alias("x")), "a")
    both = left.join(sets.select(F.col("doc_id").alias("b"), F.col("hashes").alias("y")), "b")
    shared = F.size(F.array_intersect("x", "y")).cast("long")
    return both.withColumn("shared", shared).where(F.col("shared") * 100 >= (F.size("x") + F.size("y") - F.col("shared")) * percent).select("a", "b")


def components(links: DataFrame) -> DataFrame:
    """(node, component) of the nodes of links (a, b); component is the least node reachable.

    Each node is joined to the least of its neighbours and itself, first for its larger neighbours, then for its
    smaller ones, until nothing changes; every round is an aggregate and a join that skew handling can split.
    """
    edges = links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    edges = keep(edges)

    def look(table: DataFrame) -> tuple:
        return tuple(table.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first())

    state = look(edges)
    while state[0]:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        large = keep(large)
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v")
        edges = keep(small.where("u <> v").distinct())
        before, state = state, look(edges)
        if state == before:
            break
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)


def class_links(classes: DataFrame, docs: DataFrame, percent: int = PERCENT, least_agreement: int = LEAST_AGREEMENT) -> DataFrame:
    """All links that are needed between classes (node, size, bands, marks): (a, b), a < b, each verified."""
    rows = classes.select("node", F.explode("bands").alias("band"))
    met = rows.groupBy("band").agg(F.min("node").alias("first"), F.max("node").alias("last"), F.count(F.lit(1)).alias("n")).where("first < last").select("band", "n")
    members = keep(rows.join(met, "band"))
    # Of a group's copies the ones nearest to its middle stand in most and largest bands: they are the centres.
    weight = members.groupBy("node").agg(F.sum("n").alias("w"))
    about = keep(classes.join(weight, "node").select("node", "size", "marks", "w"))
    middle = members.select("band", "node").join(about.select("node", "w"), "node")
    rank = F.struct("w", (-F.col("node")).alias("m"))
    centres = keep(middle.groupBy("band").agg(F.max(rank).alias("x")).select("band", (-F.col("x.m")).alias("centre"), F.col("x.w").alias("cw")))
    spokes = keep(members.select("band", "node").join(centres, "band").where("centre <> node").select("band", "node", "centre", "cw"))
    # The list of candidates grows with the data: it is never broadcast, however short it happens to be.
    sets = keep(full_sets(docs.join(about.select("node").hint("merge"), docs["doc_id"] == F.col("node"), "left_semi")))

    best = spokes.groupBy("node").agg(F.max(F.struct("cw", (-F.col("centre")).alias("m"))).alias("x")).select("node", (-F.col("x.m")).alias("centre"))
    tried = keep(best.select(F.least("node", "centre").alias("a"), F.greatest("node", "centre").alias("b")).distinct())
    links = keep(verified(tried, sets, percent))
    own = alone(lambda: components(links))

    def placed(table: DataFrame, key: str, name: str) -> DataFrame:
        mine = own.select(F.col("node").alias(key), F.col("component").alias(name))
        return table.join(mine, key, "left").withColumn(name, F.coalesce(name, key))

    def compared(pairs: DataFrame) -> DataFrame:
        """New pairs (a, b) that weren't tried before and whose sketches agree."""
        new = pairs.distinct().join(tried, ["a", "b"], "left_anti")
        for side in ("a", "b"):
            new = new.join(about.select(F.col("node").alias(side), F.col("size").alias(f"size_{side}"), F.col("marks").alias(f"marks_{side}")), side)
        return keep(agreement(new.where(may_reach(F.col("size_a"), F.col("size_b"), percent)), least_agreement).distinct())

    stars = placed(placed(spokes.select(F.least("node", "centre").alias("a"), F.greatest("node", "centre").alias("b")).distinct(), "a", "ca"), "b", "cb")
    candidates = compared(stars.where("ca <> cb").select("a", "b"))
    links = keep(links.unionByName(verified(candidates, sets, percent)))
    tried = keep(tried.unionByName(candidates))
    own = alone(lambda: components(links))

    with_own = keep(placed(members.select("band", "node"), "node", "component"))
    parts = with_own.groupBy("band", "component").agg(F.count(F.lit(1)).alias("n"))
    mixed = parts.groupBy("band").agg(F.count(F.lit(1)).alias("parts"), F.sum("n").alias("all"), F.max_by("component", F.struct("n", F.col("component"))).alias("main")).where("parts > 1 and all > 2").select("band", "main")
    undecided = with_own.join(mixed, "band").groupBy("node").agg(F.max("component").alias("component"), F.max(F.col("component") != F.col("main")).alias("stray"))
    undecided = keep(undecided)
    candidates = keep(prefix_pairs(undecided, sets, percent).join(tried, ["a", "b"], "left_anti"))
    return links.unionByName(verified(candidates, sets, percent))


def prefix_pairs(nodes: DataFrame, sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(a, b): pairs of a stray and another node (node, component, stray) of different components that can reach the
    similarity, by the exact prefix and position filters of set-similarity joins. A node may have several sets.

    Elements are ordered from the rarest. Sets that reach the similarity share an element within the first
    n - ceil(t n) + 1 of the larger and the first n - ceil(2 t n / (1 + t)) + 1 of the smaller one, and behind the
    first shared one, at the places i and j, 1 + least(n - i, m - j) elements can be shared at most. A copy whose own
    changes already fill its prefix shares none, so that it is cleared without meeting the others of its group."""
    t, both = percent, 100 + percent
    each = sets.join(nodes.select(F.col("node").alias("doc_id")), "doc_id", "left_semi").select(F.col("doc_id").alias("node"), F.xxhash64("hashes").alias("own"), F.size("hashes").alias("size"), F.explode("hashes").alias("h"))
    often = each.groupBy("h").agg(F.count(F.lit(1)).alias("df"))
    placed = each.join(often, "h").withColumn("place", F.row_number().over(Window.partitionBy("node", "own").orderBy("df", "h")))
    placed = placed.join(nodes, "node").where((F.col("df") > 1) & (F.col("place") <= F.col("size") - F.ceil(F.col("size") * t / 100.0 - 1e-9) + 1))
    placed = keep(placed.withColumn("short", F.col("size") - F.ceil(F.col("size") * 2 * t / float(both) - 1e-9) + 1).select("node", "h", "place", "size", "component", "stray", "short"))
    x = placed.where("stray").select("h", *(F.col(c).alias(f"x_{c}") for c in ("node", "place", "size", "component", "short")))
    y = placed.select("h", *(F.col(c).alias(f"y_{c}") for c in ("node", "place", "size", "component", "short", "stray")))
    smaller = (F.col("x_size") < F.col("y_size")) | ((F.col("x_size") == F.col("y_size")) & (F.col("x_node") < F.col("y_node")))
    within = F.when(smaller, F.col("x_place") <= F.col("x_short")).otherwise(F.col("y_place") <= F.col("y_short"))
    reach = (F.least(F.col("x_size") - F.col("x_place"), F.col("y_size") - F.col("y_place")) + 1) * both >= (F.col("x_size") + F.col("y_size")) * t
    once = ~F.col("y_stray") | (F.col("x_node") < F.col("y_node"))
    met = x.join(y, (x["h"] == y["h"]) & (F.col("x_component") != F.col("y_component")) & once & within & reach & may_reach(F.col("x_size"), F.col("y_size"), percent))
    return met.select(F.least("x_node", "y_node").alias("a"), F.greatest("x_node", "y_node").alias("b")).distinct()


def near_duplicates(docs: DataFrame, percent: int = PERCENT, least_agreement: int = LEAST_AGREEMENT) -> DataFrame:
    """doc_id, n_shingles, component_id, kept, one row per row of docs. least_agreement=0 verifies all candidates."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    marked = keep(signatures(docs))
    full = marked.where("n_shingles > 0 and doc_id is not null")
    classes = keep(full.groupBy("f1", "f2", "n_shingles").agg(F.min("doc_id").alias("node"), F.count(F.lit(1)).alias("copies")))
    heads = classes.select(F.col("node"), F.col("f1").alias("g1"), F.col("f2").alias("g2")).distinct()
    head = full.join(heads, (full["doc_id"] == heads["node"]) & (full["f1"] == heads["g1"]) & (full["f2"] == heads["g2"]), "left_semi")
    head = head.select(F.col("doc_id").alias("node"), F.col("n_shingles").alias("size"), "bands", "marks")
    links = alone(lambda: class_links(head, docs, percent, least_agreement))
    # A doc_id that stands on rows of several classes links them.
    again = full.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id")
    again = keep(full.select("doc_id", "f1", "f2", "n_shingles").join(again, "doc_id").distinct().join(classes, ["f1", "f2", "n_shingles"]).select("doc_id", "node"))
    least = again.groupBy("doc_id").agg(F.min("node").alias("b"))
    own = alone(lambda: components(links.unionByName(again.join(least, "doc_id").select(F.col("node").alias("a"), "b"))))
    named = classes.join(own, "node", "left").select("f1", "f2", "n_shingles", F.coalesce("component", "node").alias("component"), (F.col("copies") > 1).alias("several"), "node")
    # Only classes of several documents or with links need a join; the others are their own component.
    told = named.where("several or component <> node").select("f1", "f2", "n_shingles", "component")
    out = marked.select("doc_id", "n_shingles", "f1", "f2").join(told, ["f1", "f2", "n_shingles"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def deduplicated(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """docs without the documents whose component has a smaller doc_id."""
    gone = alone(lambda: near_duplicates(docs, percent).where("not kept").select(F.col("doc_id").alias("gone")).distinct())
    rows = docs.select(F.struct(*(F.col(f"`{n}`") for n in docs.columns)).alias("row"), F.col("doc_id").cast("long").alias("own"))
    return rows.join(gone, F.col("own") == F.col("gone"), "left_anti").select("row.*")
