"""Language-model scores: an add-one unigram base over words and a probabilistic suffix tree over bytes.

Tokens are the words, A-Z lower-cased, and one end per text. The tree predicts the bytes of the words joined by one
space, and an end; a text's score is the log10 probability of that byte sequence, which stands for its tokens one
to one. The end is the symbol 0; a NUL in a text is written as 0xFF, which UTF-8 never uses.

Windows. Each predicted byte gives one window: the DEPTH bytes before it (zeros before the start), the nearest first,
and itself. In this order the windows of one context suffix are neighbours.
Growing. A context is a candidate if it precedes at least LEAST bytes of the training texts: a count, so that the tree
grows with the corpus. It is retained if its next-byte distribution diverges from that of the suffix that is one byte
shorter: the count times the Kullback-Leibler divergence must reach DIVERGENCE nats for each different next byte (a
likelihood-ratio test). The suffixes of retained contexts are retained; candidates of up to SHALLOW bytes always are.
Smoothing. A state gives n(s) + t * q(s) over n + t, with n its count, t its number of different next bytes and q
the distribution of its longest proper suffix; below the empty context stands the uniform distribution.
Scoring. The longest retained suffix of what was read is the state of each byte.

Spread. No task holds the tree, and the driver only its first levels (contexts of up to SHALLOW bytes, at most
256 ** (SHALLOW + 1) pairs), which travel to the tasks.

1. Texts are dealt into chunks of about CHUNK bytes by a hash; a chunk gives its different windows, sorted, with
   their training counts, as one packed row for each of the PARTS of the tree. A part is a hash of the last SHALLOW + 1
   context bytes, so that every deeper context lies in one part whole.
2. The rows of a part are merged, first those of one salt (a group of SALTED chunks), then the salts' results: no task
   reads the rows of more than SALTED chunks. A part is grown and gives the log probability of each of its windows.
3. These meet the chunks' rows of each salt, and a chunk gets back one number for each of its windows.

Words (64-bit hashes) go the same way: a chunk asks for its different ones, and gets their training counts.

Defined cases: a null text is empty and has the end only; a null doc_id counts as the text "" in the split; rows
that repeat a doc_id are scored each; without training texts the base is 0 and the tree uniform; a text longer than
CHUNK is scanned block by block; an empty table gives an empty result; other columns aren't read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import KeyTable, Tally, U, chunks, keep, lowered, mix, span_hashes, string_parts, word_bytes, word_spans

DEPTH = 6
SHALLOW = 2
LEAST = 4
DIVERGENCE = 2.0
CHUNK = 16_000_000
SCAN = 500_000  # bytes whose windows a task holds at once, about 50 bytes of memory each
PARTS = 512
WORD_BITS = 8  # words are dealt by the highest bits of their hash
SALTED = 256
END = 0x454E44 | 1 << 63
_FLUSH = 400_000


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 7 == 2


def normal(data: np.ndarray) -> np.ndarray:
    """Lower-cased bytes without the symbol of the end."""
    data = lowered(data)
    data[data == 0] = 255
    return data


def blocks(batch: pa.RecordBatch, held: bool | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, normal bytes, offsets) of the texts of batch (text, held), about SCAN bytes at once; where held
    is given, the bytes of such rows only. The batch isn't copied as a whole."""
    for start, end, data, at in chunks(batch["text"], SCAN):
        if held is not None:
            side = pc.equal(batch["held"].slice(start, end - start), held)
            data, at = string_parts(batch["text"].slice(start, end - start).filter(side))
        if len(at) > 1:
            yield start, end, normal(data), at


def byte_streams(data: np.ndarray, at: np.ndarray, depth: int = DEPTH) -> tuple[np.ndarray, np.ndarray]:
    """(stream, edges): for each row `depth` zeros, its words joined by single spaces, and a zero."""
    starts, ends, row = word_spans(data, at)
    n = len(at) - 1
    count = np.bincount(row, minlength=n)
    size = np.bincount(row, weights=ends - starts, minlength=n).astype(np.int64)
    edges = np.concatenate([[0], np.cumsum(depth + size + np.maximum(count - 1, 0) + 1)])
    out = np.zeros(edges[-1], np.uint8)
    if len(starts):
        again = np.concatenate([[False], row[1:] == row[:-1]])
        blanks = starts[again] - 1  # the last one before each further word of a row
        kept, data = word_bytes(data), data.copy()
        kept[blanks], data[blanks] = True, 0x20
        free = np.ones(len(out), bool)
        free[edges[1:] - 1] = False
        for k in range(depth):
            free[edges[:-1] + k] = False
        out[free] = data[kept]
    return out, edges


def windows(stream: np.ndarray, edges: np.ndarray, depth: int = DEPTH) -> tuple[np.ndarray, np.ndarray]:
    """(codes, rows) of the predicted bytes: the `depth` bytes before, the nearest highest, then the byte itself."""
    n = len(stream) - depth
    code = np.zeros(max(n, 0), U)
    for j in range(1, depth + 1):
        code |= stream[depth - j : depth - j + n].astype(U) << U(8 * (depth + 1 - j))
    code |= stream[depth:].astype(U)
    size = np.diff(edges)
    rows = np.repeat(np.arange(len(size)), size)[depth:]
    inside = np.ones(len(code), bool)
    for k in range(depth):  # windows that end in the next row's zeros
        inside[edges[1:-1] + k - depth] = False
    return code[inside], rows[inside]


def pair_codes(codes: np.ndarray, full: int, depth: int) -> np.ndarray:
    """Windows of `full` context bytes cut to the nearest `depth` ones."""
    return ((codes >> U(8 * (full - depth + 1))) << U(8)) | (codes & U(255))


def summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different keys, sorted, with the sum of their counts."""
    if not len(keys):
        return keys, counts
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[first], np.add.reduceat(counts, first)


def planes(values: np.ndarray) -> bytes:
    """64-bit numbers by byte planes: the high ones are zeros, which compress to nothing."""
    return np.ascontiguousarray(values.view(np.uint8).reshape(-1, 8).T).tobytes()


def from_planes(raw: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, -1).T).view(U).ravel()


def packed(keys: np.ndarray) -> bytes:
    """Sorted keys as planes of their differences."""
    return planes(np.diff(keys, prepend=U(0)))


def unpacked(raw: bytes) -> np.ndarray:
    return np.cumsum(from_planes(raw), dtype=U)


def gathered(docs: DataFrame) -> DataFrame:
    """kind, k, n over docs (text, held): counts of shallow windows (0) and words (1; the ends are words) in the
    training texts, and the bytes of all texts (2)."""

    def rows(kind: int, k: np.ndarray, n: np.ndarray) -> Iterator[pa.RecordBatch]:
        for i in range(0, len(k), 100_000):
            part = k[i : i + 100_000].view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), kind, np.int8)), pa.array(part), pa.array(n[i : i + 100_000])], ["kind", "k", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, words, ends, size = Tally(), Tally(), 0, 0
        for b in batches:
            size += sum(len(data) for _, _, data, _ in chunks(b["text"]))
            for _, _, data, at in blocks(b, False):
                with np.errstate(over="ignore"):
                    seen.add(windows(*byte_streams(data, at, SHALLOW), SHALLOW)[0])
                    spans = word_spans(data, at)
                    words.add(span_hashes(data, *spans[:2]))
                ends += len(at) - 1
                if len(words.keys) > _FLUSH:  # sums follow in any case: what a task holds stays bounded
                    yield from rows(1, *words.cleared())
        yield from rows(0, *seen.cleared())
        yield from rows(1, *words.cleared())
        yield from rows(1, np.array([END], U), np.array([ends]))
        yield from rows(2, np.zeros(1, U), np.array([size]))

    counts = docs.select(F.coalesce("text", F.lit("")).alias("text"), "held").mapInArrow(run, "kind tinyint, k long, n long")
    return counts.where("n > 0").groupBy("kind", "k").agg(F.sum("n").alias("n"))


@dataclass
class Level:
    """Contexts, log10 of their escape; pairs (context and byte), log10 of their probability. All sorted."""

    contexts: np.ndarray
    escapes: np.ndarray
    pairs: np.ndarray
    logs: np.ndarray
    counts: np.ndarray  # training bytes behind each context
    tables: tuple[KeyTable, KeyTable] | None = None

    def prepared(self) -> tuple[KeyTable, KeyTable]:
        if self.tables is None:
            self.tables = KeyTable(self.pairs), KeyTable(self.contexts)
        return self.tables


@dataclass
class Tree:
    levels: dict[int, Level] = field(default_factory=dict)

    def score(self, codes: np.ndarray, full: int) -> np.ndarray:
        """log10 probability of the last byte of each window of `full` context bytes."""
        out, left = np.zeros(len(codes)), np.arange(len(codes))
        for d in sorted((d for d in self.levels if d <= full), reverse=True):
            level = self.levels[d]
            pairs, contexts = level.prepared()
            key = pair_codes(codes[left], full, d)
            at = pairs.find(key)
            hit = at >= 0
            out[left[hit]] += level.logs[at[hit]]
            left, key = left[~hit], key[~hit]
            at = contexts.find(key >> U(8))
            known = at >= 0
            out[left[known]] += level.escapes[at[known]]
        out[left] -= np.log10(256)
        return out


def grow(codes: np.ndarray, counts: np.ndarray, full: int, depths: range, below: Tree | None = None, ratios: tuple[np.ndarray, np.ndarray] | None = None, least: int = LEAST, divergence: float = DIVERGENCE) -> tuple[Tree, tuple[np.ndarray, np.ndarray]]:
    """The levels `depths` of the tree of sorted windows (with all windows of each of these contexts), on top of
    `below`; and (pairs, share in their context) of the deepest candidates, which a further call takes as `ratios`."""
    seen = counts > 0
    codes, counts = codes[seen], counts[seen]
    parts, kept = {}, {}
    for d in depths:
        k, n = (codes, counts) if d == full else summed(pair_codes(codes, full, d), counts)
        c = k >> U(8)
        first = np.flatnonzero(np.concatenate([[True], c[1:] != c[:-1]])) if len(k) else np.zeros(0, np.int64)
        size = np.diff(np.append(first, len(k)))
        m = np.add.reduceat(n, first) if len(k) else n
        enough = m >= least
        wide = np.repeat(enough, size)
        k, n, c, m, size = k[wide], n[wide], c[first][enough], m[enough], size[enough]
        share = n / np.repeat(m, size)
        if d > SHALLOW:
            shorter = ((k >> U(16)) << U(8)) | (k & U(255))  # its context has at least this one's count
            gain = n * np.log(share / ratios[1][KeyTable(ratios[0]).find(shorter)])
            kept[d] = np.add.reduceat(gain, np.cumsum(size) - size) >= divergence * size if len(c) else np.zeros(0, bool)
        else:
            kept[d] = np.ones(len(c), bool)
        parts[d], ratios = (k, n, c, m, size), (k, share)
    for d in reversed(depths[1:]):  # suffixes of what stays
        if d > SHALLOW + 1:
            kept[d - 1][KeyTable(parts[d - 1][2]).find(np.unique(parts[d][2][kept[d]] >> U(8)))] = True
    tree = Tree(dict(below.levels) if below else {})
    for d in depths:
        k, n, c, m, size = parts[d]
        wide = np.repeat(kept[d], size)
        c, m, t, k, n = c[kept[d]], m[kept[d]], size[kept[d]], k[wide], n[wide]
        q = 10 ** tree.score(k, d)
        tree.levels[d] = Level(c, np.log10(t / (m + t)), k, np.log10((n + np.repeat(t, t) * q) / np.repeat(m + t, t)), m)
    return tree, ratios


def merged(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    return summed(np.concatenate([unpacked(x) for x in table["keys"].to_pylist()]), np.concatenate([from_planes(x) for x in table["counts"].to_pylist()]).view(np.int64))


def chunk_windows(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Different windows of a chunk's texts, sorted, and their counts in the training texts."""
    train, other = Tally(), Tally()
    for held, tally in ((False, train), (True, other)):
        for b in table.to_batches():
            for _, _, data, at in blocks(b, held):
                tally.add(windows(*byte_streams(data, at))[0])
        tally.settle()
    if not len(train.keys):
        return other.keys, other.counts * 0
    # Both are sorted: those that only held-out texts have are put between.
    at = np.searchsorted(train.keys, other.keys)
    new = train.keys[np.minimum(at, len(train.keys) - 1)] != other.keys
    return np.insert(train.keys, at[new], other.keys[new]), np.insert(train.counts, at[new], 0)


def in_parts(keys: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order, part of each run, edges of the runs): sorted windows by part, in their order within it."""
    with np.errstate(over="ignore"):
        part = (mix(keys >> U(8 * (DEPTH - SHALLOW))) % U(parts)).astype(np.uint16)
    order = np.argsort(part, kind="stable")
    part = part[order]
    first = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]])) if len(part) else np.zeros(0, np.int64)
    return order, part[first], np.append(first, len(part))


def chunk_words(table: pa.Table) -> np.ndarray:
    """Different words of a chunk's texts and the end, as sorted hashes."""
    seen = Tally()
    for b in table.to_batches():
        for _, _, data, at in blocks(b):
            seen.add(span_hashes(data, *word_spans(data, at)[:2]))
    seen.add(np.array([END], U))
    return seen.cleared()[0]


def dealt(docs: DataFrame, parts: int, salted: int) -> DataFrame:
    """chunk, part, salt, keys, counts of docs (with text, held, chunk); parts from `parts` on hold words, uncounted."""

    def run(key: tuple, table: pa.Table) -> pa.Table:
        with np.errstate(over="ignore"):
            keys, counts = chunk_windows(table)
            words = chunk_words(table)
        order, part, edge = in_parts(keys, parts)
        keys, counts = keys[order], counts[order]
        cut = list(zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True))
        rows = [(p, packed(keys[a:b]), planes(counts[a:b])) for p, (a, b) in zip(part.tolist(), cut, strict=True)]
        edge = np.searchsorted(words >> U(64 - WORD_BITS), np.arange((1 << WORD_BITS) + 1))
        rows += [(parts + p, packed(words[a:b]), b"") for p, (a, b) in enumerate(zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)) if a < b]
        chunk = key[0].as_py()
        return pa.table({
            "chunk": pa.array([chunk] * len(rows), pa.int64()), "part": pa.array([r[0] for r in rows], pa.int32()), "salt": pa.array([chunk // salted] * len(rows), pa.int32()),
            "keys": pa.array([r[1] for r in rows], pa.binary()), "counts": pa.array([r[2] for r in rows], pa.binary()),
        })

    return docs.groupBy("chunk").applyInArrow(run, "chunk long, part int, salt int, keys binary, counts binary")


def part_counts(rows: DataFrame, parts: int) -> DataFrame:
    """part, keys, counts: the rows of each part of the tree and salt merged."""

    def run(key: tuple, table: pa.Table) -> pa.Table:
        some = [] if key[0].as_py() >= parts else [merged(table)]
        return pa.table({"part": pa.array([key[0].as_py()] * len(some), pa.int32()), "keys": pa.array([packed(k) for k, _ in some], pa.binary()), "counts": pa.array([planes(n) for _, n in some], pa.binary())})

    return rows.groupBy("part", "salt").applyInArrow(run, "part int, keys binary, counts binary")


def word_parts(words: DataFrame, parts: int) -> DataFrame:
    """part, keys, logs: the words of each part and (here as they are) their counts."""

    def run(key: tuple, table: pa.Table) -> pa.Table:
        keys, counts = summed(table["h"].to_numpy().view(U), table["c"].to_numpy())
        return pa.table({"part": pa.array([parts + key[0].as_py()], pa.int32()), "keys": pa.array([packed(keys)], pa.binary()), "logs": pa.array([planes(counts)], pa.binary())})

    rows = words.withColumn("part", F.shiftrightunsigned("h", 64 - WORD_BITS).cast("int"))
    return rows.groupBy("part").applyInArrow(run, "part int, keys binary, logs binary")


def part_logs(counts: DataFrame, shared, least: int, divergence: float) -> DataFrame:
    """part, keys, logs: the log10 probability of every window of the part, by its own subtree."""

    def run(key: tuple, table: pa.Table) -> pa.Table:
        first, ratios = shared.value
        keys, n = merged(table)
        with np.errstate(over="ignore"):
            tree, _ = grow(keys, n, DEPTH, range(SHALLOW + 1, DEPTH + 1), first, ratios, least, divergence)
            logs = tree.score(keys, DEPTH)
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "keys": pa.array([packed(keys)], pa.binary()), "logs": pa.array([logs.astype(np.float32).tobytes()], pa.binary())})

    return counts.groupBy("part").applyInArrow(run, "part int, keys binary, logs binary")


def chunk_logs(rows: DataFrame, logs: DataFrame, parts: int) -> DataFrame:
    """chunk, part, logs: for the windows or words of each row of `rows`, in their order."""

    def run(key: tuple, asked: pa.Table, known: pa.Table) -> pa.Table:
        out = []
        if asked.num_rows:
            words = key[0].as_py() >= parts
            keys, values = np.zeros(0, U), np.zeros(0, np.int64)  # words that no training text has
            if known.num_rows:
                keys, raw = unpacked(known["keys"][0].as_py()), known["logs"][0].as_py()
                values = from_planes(raw).view(np.int64) if words else np.frombuffer(raw, np.float32)
            for x in asked["keys"].to_pylist():
                x = unpacked(x)
                at = np.minimum(np.searchsorted(keys, x), max(len(keys) - 1, 0))
                if words:
                    out.append(planes(np.where(keys[at] == x, values[at], 0) if len(keys) else np.zeros(len(x), np.int64)))
                else:
                    out.append(values[at].tobytes())
        return pa.table({"chunk": asked["chunk"].cast(pa.int64()), "part": asked["part"].cast(pa.int32()), "logs": pa.array(out, pa.binary())})

    # All columns of rows, as in `part_counts`: both read one exchange.
    return rows.groupBy("part", "salt").cogroup(logs.groupBy("part", "salt")).applyInArrow(run, "chunk long, part int, logs binary")


@dataclass
class Counted:
    """What the driver knows of a corpus: bounded numbers only."""

    words: DataFrame  # h, c
    tokens: int
    different: int
    size: int
    tree: Tree
    ratios: tuple[np.ndarray, np.ndarray]


def counted(docs: DataFrame, least: int = LEAST) -> Counted:
    counts = keep(gathered(docs))
    sums = {r["kind"]: (r["n"], r["v"]) for r in counts.groupBy("kind").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("v")).collect()}
    table = counts.where("kind = 0").select("k", "n").toArrow()  # at most 256 ** (SHALLOW + 1) rows
    codes, n = summed(table["k"].to_numpy().view(U), table["n"].to_numpy()) if table.num_rows else (np.zeros(0, U), np.zeros(0, np.int64))
    with np.errstate(over="ignore"):
        tree, ratios = grow(codes, n, SHALLOW, range(SHALLOW + 1), least=least)
    words = counts.where("kind = 1").select(F.col("k").alias("h"), F.col("n").alias("c"))
    return Counted(words, *sums.get(1, (0, 0)), sums.get(2, (0, 0))[0], tree, ratios)


def prepared(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), held_out(F.col("doc_id").cast("long")).alias("held"))


def in_chunks(docs: DataFrame, size: int, chunk: int) -> tuple[DataFrame, int]:
    """docs with u and chunk (by a hash of the row, so that a task that is run again deals alike), and their number."""
    n = max(1, round(size / chunk))
    return docs.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text"), F.lit(n))), n


def states(docs: DataFrame, least: int = LEAST, divergence: float = DIVERGENCE, parts: int = PARTS, salted: int = SALTED, chunk: int = CHUNK) -> DataFrame:
    """context (bytes, the nearest last), n, kinds (different next bytes): the retained contexts of docs' training
    texts that are longer than SHALLOW."""
    docs = prepared(docs)
    known = counted(docs, least)
    rows, _ = in_chunks(docs, known.size, chunk)
    shared = docs.sparkSession.sparkContext.broadcast((known.tree, known.ratios))

    def run(key: tuple, table: pa.Table) -> pa.Table:
        with np.errstate(over="ignore"):
            tree, _ = grow(*merged(table), DEPTH, range(SHALLOW + 1, DEPTH + 1), *shared.value, least, divergence)
        context, count, kinds = [], [], []
        for d in range(SHALLOW + 1, DEPTH + 1):
            level = tree.levels[d]
            context += [int(c).to_bytes(d, "big")[::-1] for c in level.contexts]
            count.append(level.counts)
            kinds.append(np.diff(np.searchsorted(level.pairs >> U(8), np.append(level.contexts, U(1 << 8 * d)))) if len(level.contexts) else np.zeros(0, np.int64))
        return pa.table({"context": pa.array(context, pa.binary()), "n": pa.array(np.concatenate(count), pa.int64()), "kinds": pa.array(np.concatenate(kinds), pa.int64())})

    return part_counts(dealt(rows, parts, salted), parts).groupBy("part").applyInArrow(run, "context binary, n long, kinds long")


def scores(docs: DataFrame, least: int = LEAST, divergence: float = DIVERGENCE, parts: int = PARTS, salted: int = SALTED, chunk: int = CHUNK) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row of docs."""
    docs = prepared(docs)
    spark = docs.sparkSession
    known = counted(docs, least)
    total = known.tokens
    below = float(np.log10(total + known.different + 1))
    shallow = spark.sparkContext.broadcast((known.tree, known.ratios))
    rows, n_chunks = in_chunks(docs, known.size, chunk)
    asked = dealt(rows, parts, salted)
    logs = part_logs(part_counts(asked, parts), shallow, least, divergence).unionByName(word_parts(known.words, parts))
    logs = logs.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit((n_chunks - 1) // salted))))
    back = chunk_logs(asked, logs, parts)
    names = ["doc_id", "n_tokens", "n_known", "base", "score"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64()]

    def run(key: tuple, texts: pa.Table, logs: pa.Table) -> pa.Table:
        out = [pa.table([pa.array([], k) for k in kinds], names)]
        if texts.num_rows:
            mine = dict(zip(logs["part"].to_pylist(), logs["logs"].to_pylist(), strict=True))
            with np.errstate(over="ignore"):
                codes, _ = chunk_windows(texts)
                order, part, _ = in_parts(codes, parts)
                values = np.empty(len(codes), np.float32)
                values[order] = np.concatenate([np.frombuffer(mine[p], np.float32) for p in part.tolist()])
                del order
                table, words = KeyTable(codes), KeyTable(chunk_words(texts))
            times = np.concatenate([from_planes(mine[p]).view(np.int64) for p in sorted(p for p in mine if p >= parts)])
            gains, seen = np.log10(times + 1) - below, times > 0
            end_at = int(words.find(np.array([END], U))[0])
        for b in texts.to_batches():
            for start, end, data, at in blocks(b):
                n = end - start
                with np.errstate(over="ignore"):
                    code, of = windows(*byte_streams(data, at))
                    score = np.bincount(of, weights=values[table.find(code)], minlength=n)
                    starts, ends, row = word_spans(data, at)
                    found = words.find(span_hashes(data, starts, ends))
                count = np.bincount(row, minlength=n) + 1
                met = np.bincount(row, weights=seen[found], minlength=n).astype(np.int64) + int(seen[end_at])
                base = np.bincount(row, weights=gains[found], minlength=n) + gains[end_at]
                columns = zip((count, met, base, score), kinds[1:], strict=True)
                out.append(pa.table([b["doc_id"].slice(start, n), *(pa.array(x, k) for x, k in columns)], names))
        return pa.concat_tables(out)

    scored = rows.groupBy("chunk").cogroup(back.groupBy("chunk")).applyInArrow(run, "doc_id long, n_tokens long, n_known long, base double, score double")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "n_tokens", "n_known", F.lit(total).cast("long").alias("train_tokens"), F.col("base").alias("base_score"), "score")
