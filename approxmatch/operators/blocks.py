"""Many queries against many tuples, block by block: top k of a weighted sum, and pairs above a Jaccard similarity.

Tuples are split into blocks of a bounded number of tokens and queries into parts; every task gets one block and one part,
and keeps an inverted list of the block. Queries of a task are ordered by their tokens, the most frequent first, so that
neighbours share the sums over the long lists: a task walks the tree of these token sequences, adds a token's list when it
goes down and takes it back when it comes up. What changes at a step is found in that step's list alone.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Tokens of a block, queries of a part, rows of a batch of results.
BLOCK, PART, ROWS = 2_000_000, 25_000, 500_000
#: Digits to which scores are compared.
DIGITS = 9
SLACK = 2 * 10.0**-DIGITS


def _dealt(tuples: DataFrame, asked: DataFrame, tokens: int, queries: int) -> DataFrame:
    """Rows (part, kind, id, size, tokens, w, copies), each part in a task of its own: its block (kind 0), then its queries."""
    blocks = tokens // BLOCK + 1
    parts = max(tuples.sparkSession.sparkContext.defaultParallelism, queries // PART + 1)
    of = lambda n, i: F.pmod(F.xxhash64("id"), F.lit(n)).cast("int") if n > 1 else F.lit(i)
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    a = tuples.withColumn("block", of(blocks, 0)).withColumn("of", every(parts))
    b = asked.withColumn("block", every(blocks)).withColumn("of", of(parts, 0))
    part = (F.col("block") * parts + F.col("of")).alias("part")
    both = (df.select(part, F.lit(kind).alias("kind"), "id", "size", "tokens", "w", "copies") for kind, df in enumerate((a, b)))
    first, second = both
    return first.unionByName(second).repartitionById(blocks * parts, F.col("part")).sortWithinPartitions("kind", "id").drop("part")


def _lists(column: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """The values of lists, and the lists' lengths."""
    return column.flatten(), pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False)


class _Block:
    """Inverted lists of a block, tokens numbered by falling length, those with a negative weight first."""

    def __init__(self, batches: list[pa.RecordBatch]):
        rows = pa.Table.from_batches(batches).combine_chunks()
        column = lambda name: rows[name].combine_chunks() if rows[name].num_chunks != 1 else rows[name].chunk(0)
        self.ids = column("id").to_numpy()
        self.size = column("size").to_numpy().astype(np.int64)
        copies, self.n_copies = _lists(column("copies"))
        self.copies, self.copy_at = copies.to_numpy(), np.cumsum(self.n_copies) - self.n_copies
        tokens, n = _lists(column("tokens"))
        coded = tokens.dictionary_encode()
        self.words, codes = coded.dictionary, coded.indices.to_numpy()
        w = _lists(column("w"))[0].to_numpy()
        length = np.bincount(codes, minlength=len(self.words))
        least = np.zeros(len(self.words))
        if len(w):
            np.minimum.at(least, codes, w)
        order = np.lexsort((-length, least >= 0))
        self.number = np.empty(len(order), np.int64)
        self.number[order] = np.arange(len(order))
        by = np.argsort(self.number[codes], kind="stable")
        at = np.concatenate(([0], np.cumsum(length[order])))
        row = np.repeat(np.arange(len(n)), n)[by]
        self.lists = [row[x:y] for x, y in zip(at[:-1], at[1:], strict=True)]
        w = w[by] if len(w) else w
        self.weights = [v[0] if (v := w[x:y]).min() == v.max() else v for x, y in zip(at[:-1], at[1:], strict=True)] if len(w) else []
        self.negative = (least < 0)[order]

    def known(self, batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(numbers, weights, ends): tokens of the queries that the block has, by query and number."""
        tokens, n = _lists(batch["tokens"])
        found = pc.fill_null(pc.index_in(tokens, value_set=self.words), -1).to_numpy(zero_copy_only=False)
        w = _lists(batch["w"])[0].to_numpy(zero_copy_only=False)
        row, held = np.repeat(np.arange(len(n)), n), found >= 0
        row, number, w = row[held], self.number[found[held]], w[held] if len(w) else w
        order = np.lexsort((number, row))
        return number[order], w[order] if len(w) else w, np.cumsum(np.bincount(row, minlength=len(n)))


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[_Block, pa.RecordBatch]]:
    """The block and a batch of queries, one after another; none where there are no tuples."""
    held, block = [], None
    for batch in batches:
        n = pc.sum(pc.equal(batch["kind"], 0)).as_py() or 0
        if n:
            held.append(batch.slice(0, n))
        if n < batch.num_rows and (held or block):
            if block is None:
                block, held = _Block(held), []
            yield block, batch.slice(n)


def _by_tokens(keys: np.ndarray, ends: np.ndarray) -> tuple[list[list[int]], list[int]]:
    """Each query's keys, and the queries in the order of these."""
    raw = keys.astype(">i8").tobytes()
    starts = [0, *ends[:-1].tolist()]
    text = [raw[8 * x : 8 * y] for x, y in zip(starts, ends.tolist(), strict=True)]
    flat = keys.tolist()
    return [flat[x:y] for x, y in zip(starts, ends.tolist(), strict=True)], sorted(range(len(text)), key=text.__getitem__)


def _best(scores: np.ndarray, places: np.ndarray, k: int) -> list[tuple[float, int, float]]:
    """The k best (-rounded score, place, score) of different tuples; more than 64 are in the order of their places."""
    if len(scores) > 64:
        n = max(len(scores) - k, 0)
        near = (scores >= np.partition(scores, n)[n] - SLACK).nonzero()[0]
        near = near[np.round(-scores[near], DIGITS).argsort(kind="stable")[:k]]
        scores, places = scores[near], places[near]
    return sorted(zip(np.round(-scores, DIGITS).tolist(), places.tolist(), scores.tolist(), strict=True))[:k]


def _run_top_k(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    for block, batch in _read(batches):
        lists, weights, negative = block.lists, block.weights, block.negative
        number, w, ends = block.known(batch)
        values, which = np.unique(w, return_inverse=True)
        many, factors = max(len(values), 1), values.tolist()
        keys, order = _by_tokens(number * many + which, ends)
        order = [q for q in order if keys[q]]
        sums = np.zeros(len(block.ids))
        path, before, tops = [], [], [[]]  # keys on the way down, (list, sums before) of each, the best after each
        last, top = None, []
        out_q, out_p, out_s = [], [], []
        for i, q in enumerate(order):
            mine = keys[q]
            if mine != last:
                ahead = keys[order[i + 1]] if i + 1 < len(order) else []
                common = _common(path, mine[:-1])
                shared = min(max(_common(ahead, mine), common), len(mine) - 1)
                while len(path) > common:
                    at, old = before.pop()
                    sums[at] = old
                    path.pop()
                    tops.pop()
                # steps that the next query shares have their best kept; the others go as one
                for key in mine[common:shared]:
                    top = _step(sums, [key], many, factors, lists, weights, negative, before, tops[-1], k, False)
                    path.append(key)
                    tops.append(top)
                n = len(before)
                top = _step(sums, mine[shared:], many, factors, lists, weights, negative, before, tops[-1], k, True)
                while len(before) > n:
                    at, old = before.pop()
                    sums[at] = old
                last = mine
            out_q += [q] * len(top)
            out_p += [x[1] for x in top]
            out_s += [x[2] for x in top]
        qid = batch["id"].to_numpy()[np.array(out_q, np.int64)]
        yield pa.RecordBatch.from_arrays([pa.array(qid), pa.array(block.ids[np.array(out_p, np.int64)]), pa.array(np.array(out_s, float))], names=["qid", "tid", "score"])


def _common(a: list[int], b: list[int]) -> int:
    """Length of the common start."""
    n = 0
    for x, y in zip(a, b, strict=False):
        if x != y:
            break
        n += 1
    return n


def _step(sums: np.ndarray, keys: list[int], many: int, factors: list[float], lists: list[np.ndarray], weights: list[np.ndarray], negative: np.ndarray, before: list[tuple], top: list[tuple], k: int, ends: bool) -> list[tuple[float, int, float]]:
    """The k best after the lists of keys are added to sums; what was there before is put on `before`. Where a path ends,
    the last list needn't be added.

    Where nothing falls, they are among the k best of before and the tuples of these lists; sums on the way are lower
    bounds, so that what is below the k-th best of any moment is left out, and a tuple's greatest sum is its last."""
    falls = any(negative[key // many] for key in keys)
    least = -top[-1][0] - SLACK if len(top) == k else -np.inf
    near_s, near_p = [np.array([s for _, _, s in top])], [np.array([p for _, p, _ in top], np.int64)]
    for i, key in enumerate(keys):
        token, factor = divmod(key, many)
        at = lists[token]
        old = sums[at]
        new = old + factors[factor] * weights[token]
        if falls or not ends or i < len(keys) - 1:
            sums[at] = new
            before.append((at, old))
        if not falls:
            near = (new >= least).nonzero()[0]
            if len(near):
                new = new[near]
                if len(near) > 4 * k:
                    least = max(least, float(np.partition(new, len(new) - k)[len(new) - k]) - SLACK)
                    high = (new >= least).nonzero()[0]
                    near, new = near[high], new[high]
                near_s.append(new)
                near_p.append(at[near])
    if falls:
        places = np.unique(np.concatenate([at for at, _ in before]))
        return _best(sums[places], places, k)
    scores, places = np.concatenate(near_s), np.concatenate(near_p)
    high = (scores >= least).nonzero()[0]
    scores, places = scores[high], places[high]
    if len(scores) > 64:
        order = np.lexsort((scores, places))
        scores, places = scores[order], places[order]
        last = np.append(places[1:] != places[:-1], True).nonzero()[0]
        return _best(scores[last], places[last], k)
    most: dict[int, float] = {}
    for place, score in zip(places.tolist(), scores.tolist(), strict=True):
        if score > most.get(place, -np.inf):
            most[place] = score
    return _best(np.array(list(most.values())), np.array(list(most), np.int64), k)


def top_k_sums(tuples: DataFrame, asked: DataFrame, k: int, tokens: int, queries: int) -> DataFrame:
    """qid, tid, score: of (id, tokens, w) on both sides the k best tuples of each query in each block, by the sum of
    products over shared tokens (weights of queries >= 0), rounded, then id. Tuples that share nothing aren't returned."""
    shaped = lambda df: df.select("id", F.lit(0).alias("size"), "tokens", "w", F.lit(None).cast("array<long>").alias("copies"))
    return _dealt(shaped(tuples), shaped(asked), tokens, queries).mapInArrow(partial(_run_top_k, k=k), "qid long, tid long, score double")


def _run_jaccard(batches: Iterator[pa.RecordBatch], threshold: float) -> Iterator[pa.RecordBatch]:
    for block, batch in _read(batches):
        number, _, ends = block.known(batch)
        keys, order = _by_tokens(number, ends)
        size = batch["size"].to_numpy()
        least, share = int(block.size.min()), (threshold - 1e-9) / (1 + threshold - 1e-9)
        copies, n_copies = _lists(batch["copies"])
        copies, copy_at = copies.to_numpy(), np.cumsum(n_copies) - n_copies
        found, n_found = [], 0

        def emit(found: list) -> Iterator[pa.RecordBatch]:
            # pairs of heads, then a row for each copy of the tuple, then all of these for each copy of the query
            q, n = np.repeat([x[0] for x in found], [len(x[1]) for x in found]), np.concatenate([x[2] for x in found])  # noqa: B023
            p = np.concatenate([x[1] for x in found])
            score = n / (size[q] + block.size[p] - n)  # noqa: B023
            times = block.n_copies[p]  # noqa: B023
            place = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
            tid = block.copies[np.repeat(block.copy_at[p], times) + place]  # noqa: B023
            q, score = np.repeat(q, times), np.repeat(score, times)
            for i in range(int(n_copies[q].max())):  # noqa: B023
                some = n_copies[q] > i  # noqa: B023
                yield pa.RecordBatch.from_arrays([pa.array(copies[copy_at[q[some]] + i]), pa.array(tid[some]), pa.array(score[some])], names=["qid", "tid", "score"])  # noqa: B023

        lists, now = block.lists, None
        for q in sorted(order, key=lambda q: size[q]):  # noqa: B023  stable
            mine, n = keys[q], int(size[q])
            if len(mine) < max(1, int(np.ceil(share * (n + least) - 1e-9))):
                continue
            if n != now:
                now, need = n, np.maximum(np.ceil(share * (n + block.size) - 1e-9), 1).astype(np.int32)
                left, path, steps = -need, [], []  # what is missing, negative; keys on the way down; (list, counts, reached)
            common = 0
            while common < len(path) and common < len(mine) and path[common] == mine[common]:
                common += 1
            while len(path) > common:
                path.pop()
                at, counts, _ = steps.pop()
                left[at] = counts
            for token in mine[common:]:
                at = lists[token]
                counts = left[at]
                left[at] = counts + 1
                path.append(token)
                steps.append((at, counts, at[counts == -1]))
            hits = np.concatenate([x[2] for x in steps])
            if len(hits):
                found.append((q, hits, left[hits] + need[hits]))
                n_found += int(block.n_copies[hits].sum())
                if n_found > ROWS:
                    yield from emit(found)
                    found, n_found = [], 0
        if found:
            yield from emit(found)


def jaccard_pairs(tuples: DataFrame, asked: DataFrame, threshold: float, tokens: int, queries: int) -> DataFrame:
    """qid, tid, score of the pairs of copies of (id, size, tokens, copies) on both sides whose shared over united tokens
    can reach the threshold (> 0); size counts all of a row's tokens. A pair of n and m tokens shares at least
    t / (1 + t) * (n + m): a pair is found at the step where it reaches that."""
    shaped = lambda df: df.select("id", "size", "tokens", F.lit(None).cast("array<double>").alias("w"), "copies")
    return _dealt(shaped(tuples), shaped(asked), tokens, queries).mapInArrow(partial(_run_jaccard, threshold=threshold), "qid long, tid long, score double")
