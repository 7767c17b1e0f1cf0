"""Byte-level BPE by a segment tree over byte positions.

A piece (one match of the pre-tokeniser's pattern) is a row of leaves, one per byte position. The leaf of a live
part holds the rank of the pair that it forms with the next live part, or infinity; an inner node holds the least
rank below it, and of equal ranks the leftmost. The root is therefore the next merge. A merge gives the left part
its new id, takes the right part out, and updates two leaves (the merged part's own and its left neighbour's) and
the one that goes: each a path to the root.

`encode_piece` does this for one piece. `encode_pieces` does it for many pieces of like length at once, with a
tree per row of a matrix: the k-th merge of all of them is one pass of array operations. Equal pieces are encoded
once per chunk. A key packs rank and position, so that the minimum also is the leftmost.

Defined cases: a null text is empty and has no ids; a piece that is itself in the vocabulary is one id; pieces of
any length take the same path (long ones alone); ids decode to exactly the bytes of the text; of pairs with one rank the
leftmost merges first; repeated rows get equal ids; an empty table gives an empty result; other columns aren't read,
whatever their names.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import chunks

#: Pieces remembered by a worker between chunks, in two generations: those in use stay. It bounds memory only, never results.
REMEMBERED = 200_000
#: Bytes of text that are Python strings at once; of a longer text, the pieces of about as much. It bounds memory only.
CHUNK_BYTES = 1_000_000
LONG = 128
_NONE = np.int64(1) << 60


class Vocabulary:
    """Ranks of byte strings, and the ranks of pairs of ids."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.pattern = regex.compile(pattern)
        self.bytes_of = [b""] * (max(ranks.values()) + 1)
        for token, rank in ranks.items():
            self.bytes_of[rank] = token
        missing = [i for i in range(256) if bytes([i]) not in ranks]
        if missing:
            raise ValueError(f"no rank for the bytes {missing[:5]}")
        self.byte_id = np.array([ranks[bytes([i])] for i in range(256)], np.int64)
        pairs = {}
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                a, b = ranks.get(token[:cut]), ranks.get(token[cut:])
                if a is not None and b is not None:
                    pairs[a << 32 | b] = rank
        self.pairs = pairs
        keys = np.fromiter(pairs.keys(), np.int64, len(pairs))
        order = np.argsort(keys)
        self._keys, self._ranks = keys[order], np.fromiter(pairs.values(), np.int64, len(pairs))[order]
        # An open-addressing table: a few probes of a vector instead of a search of the sorted keys.
        self._bits = max(4, int(len(keys) * 2).bit_length())
        size = 1 << self._bits
        self._slot_key, self._slot_rank = np.full(size, -1, np.int64), np.full(size, _NONE, np.int64)
        left, probe = np.arange(len(keys)), 0
        while len(left):
            at = (self._home(self._keys[left]) + probe) & (size - 1)
            empty = self._slot_key[at] < 0
            mine = left[empty]
            self._slot_key[at[empty]] = self._keys[mine]  # of several, the last stays
            placed = self._slot_key[at[empty]] == self._keys[mine]
            self._slot_rank[at[empty][placed]] = self._ranks[mine[placed]]
            left = np.concatenate([left[~empty], mine[~placed]])
            probe += 1
        self.probes = probe

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self._bits)).astype(np.int64)

    def pair_ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of each pair of ids; _NONE without one (b below 0: no right neighbour)."""
        keys = a << 32 | np.maximum(b, 0)
        out = np.full(len(keys), _NONE, np.int64)
        left, at = np.flatnonzero(b >= 0), None
        at = self._home(keys[left])
        for _ in range(self.probes):
            if not len(left):
                break
            found = self._slot_key[at]
            hit = found == keys[left]
            out[left[hit]] = self._slot_rank[at[hit]]
            go = ~hit & (found >= 0)
            left, at = left[go], (at[go] + 1) & ((1 << self._bits) - 1)
        return out


@lru_cache(maxsize=4)
def load(path: str, pattern: str) -> Vocabulary:
    """A .tiktoken file: lines of base64 and rank."""
    with open(path, "rb") as f:
        return Vocabulary({base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}, pattern)


def encode_piece(piece: bytes, v: Vocabulary) -> list[int]:
    """Ids of one piece: the plain form of the method."""
    if piece in v.ranks:
        return [v.ranks[piece]]
    n, pairs = len(piece), v.pairs
    shift = max(1, (n - 1).bit_length())
    # A key is a rank above a position of `shift` bits; Python integers have no upper end.
    width, low, none = 1 << shift, (1 << shift) - 1, 1 << 64 + shift
    ids = [v.ranks[piece[i : i + 1]] for i in range(n)]
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    tree = [none] * (2 * width)
    for i in range(n - 1):
        r = pairs.get(ids[i] << 32 | ids[i + 1])
        if r is not None:
            tree[width + i] = r << shift | i
    for k in range(width - 1, 0, -1):
        tree[k] = min(tree[2 * k], tree[2 * k + 1])

    def put(i: int, value: int) -> None:
        k = width + i
        tree[k] = value
        k >>= 1
        while k:
            least = min(tree[2 * k], tree[2 * k + 1])
            if tree[k] == least:
                return
            tree[k] = least
            k >>= 1

    alive = [True] * n
    while tree[1] < none:
        rank, i = tree[1] >> shift, tree[1] & low
        j = after[i]
        ids[i], alive[j] = rank, False
        after[i] = after[j]
        if after[j] < n:
            before[after[j]] = i
        put(j, none)
        r = pairs.get(ids[i] << 32 | ids[after[i]]) if after[i] < n else None
        put(i, none if r is None else r << shift | i)
        if before[i] >= 0:
            r = pairs.get(ids[before[i]] << 32 | ids[i])
            put(before[i], none if r is None else r << shift | before[i])
    return [x for x, here in zip(ids, alive, strict=True) if here]


def encode_pieces(pieces: list[bytes], v: Vocabulary) -> list[list[int]]:
    """Ids of many different pieces of at most LONG bytes, none of them in the vocabulary."""
    out: list[list[int]] = [[] for _ in pieces]
    lengths = np.fromiter(map(len, pieces), np.int64, len(pieces))
    for low, high in ((1, 4), (4, 8), (8, 16), (16, 32), (32, 64), (64, LONG)):
        which = np.flatnonzero((lengths > low) & (lengths <= high) | ((lengths == 1) & (low == 1)))
        for part in np.array_split(which, max(1, len(which) * high // 400_000)):
            if len(part):
                _encode_block([pieces[i] for i in part], lengths[part], high, v, part, out)
    return out


def _encode_block(pieces: list[bytes], n: np.ndarray, width: int, v: Vocabulary, where: np.ndarray, out: list[list[int]]) -> None:
    rows, shift = len(pieces), np.int64(8)
    raw = np.frombuffer(b"".join(p.ljust(width, b"\0") for p in pieces), np.uint8).reshape(rows, width)
    place = np.arange(width, dtype=np.int64)
    ids = v.byte_id[raw]
    inside = place < n[:, None]
    ids[~inside] = -1
    after = np.where(place + 1 < n[:, None], place + 1, -1)
    before = np.where(inside, place - 1, -1)
    tree = np.full((rows, 2 * width), _NONE, np.int64)
    here = place[:-1] + 1 < n[:, None]
    r = v.pair_ranks(ids[:, :-1][here], ids[:, 1:][here])
    leaves = np.full((rows, width - 1), _NONE, np.int64)
    leaves[here] = np.where(r < _NONE, r << shift | np.nonzero(here)[1], _NONE)
    tree[:, width : 2 * width - 1] = leaves
    k = width
    while k > 1:
        half = k // 2
        tree[:, half:k] = np.minimum(tree[:, k : 2 * k : 2], tree[:, k + 1 : 2 * k : 2])
        k = half

    def put(row: np.ndarray, at: np.ndarray, value: np.ndarray | np.int64) -> None:
        node = at + width
        tree[row, node] = value
        node = node >> 1
        while node[0]:  # all leaves are on one level
            tree[row, node] = np.minimum(tree[row, 2 * node], tree[row, 2 * node + 1])
            node = node >> 1

    def key(row: np.ndarray, at: np.ndarray) -> np.ndarray:
        right = after[row, at]
        rank = v.pair_ranks(ids[row, at], np.where(right >= 0, ids[row, right], -1))
        return np.where(rank < _NONE, rank << shift | at, _NONE)

    row = np.flatnonzero(tree[:, 1] < _NONE)
    while len(row):
        best = tree[row, 1]
        i = best & ((1 << 8) - 1)
        j = after[row, i]
        ids[row, i] = best >> shift
        ids[row, j] = -1
        beyond = after[row, j]
        after[row, i] = beyond
        more = beyond >= 0
        before[row[more], beyond[more]] = i[more]
        put(row, j, _NONE)
        put(row, i, key(row, i))
        left = before[row, i]
        has = left >= 0
        if has.any():
            put(row[has], left[has], key(row[has], left[has]))
        row = row[tree[row, 1] < _NONE]
    live = ids >= 0
    flat, ends = ids[live].tolist(), np.cumsum(live.sum(1)).tolist()
    start = 0
    for at, end in zip(where.tolist(), ends, strict=True):
        out[at] = flat[start:end]
        start = end


class Encoder:
    """Encodes texts with a vocabulary, remembering pieces met before."""

    def __init__(self, v: Vocabulary):
        self.v = v
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}

    def learn(self, pieces: set[str]) -> None:
        """`known` has the ids of all of these pieces, until pieces are learned again."""
        if len(self.known) > REMEMBERED // 2:
            self.known, self.older = {}, self.known
        known, older, v = self.known, self.older, self.v
        short: list[tuple[str, bytes]] = []
        for p in pieces:
            if p in known:
                continue
            ids = older.get(p)
            if ids is not None:
                known[p] = ids
                continue
            raw = p.encode()
            rank = v.ranks.get(raw)
            if rank is not None:
                known[p] = np.array([rank], "<u4").tobytes()
            elif len(raw) > LONG:
                known[p] = np.array(encode_piece(raw, v), "<u4").tobytes()
            else:
                short.append((p, raw))
        for (p, _), ids in zip(short, encode_pieces([raw for _, raw in short], v), strict=True):
            known[p] = np.array(ids, "<u4").tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text, as little-endian unsigned 32-bit integers."""
        if sum(map(len, texts)) <= CHUNK_BYTES:
            return self._ids([self.v.pattern.findall(t) for t in texts])
        return [b"".join(self._ids([part])[0] for part in self._parts(t)) for t in texts]

    def _parts(self, text: str) -> Iterator[list[str]]:
        """The pieces of a text, in order, a bounded number at once."""
        found = (m.group() for m in self.v.pattern.finditer(text))
        while part := list(islice(found, CHUNK_BYTES // 4)):
            yield part

    def _ids(self, split: list[list[str]]) -> list[bytes]:
        pieces = set().union(*split)
        self.learn(pieces)
        known = self.known
        out = [b"".join([known[p] for p in parts]) for parts in split]
        for p in pieces:
            if len(p) > LONG:  # rare and of any size: not remembered
                del known[p]
        return out

    def decode(self, ids: bytes) -> bytes:
        table, every = self.v.bytes_of, np.frombuffer(ids, "<u4")
        return b"".join([b"".join([table[i] for i in every[k : k + CHUNK_BYTES // 4].tolist()]) for k in range(0, len(every), CHUNK_BYTES // 4)])


def _with_bounds(path: str, pattern: str):
    """The vocabulary's bytes travel with the task: executors need not have the file."""
    with open(path, "rb") as f:
        return f.read(), pattern


@lru_cache(maxsize=2)
def _parsed(raw: bytes, pattern: str) -> Vocabulary:
    return Vocabulary({base64.b64decode(a): int(b) for a, b in map(bytes.split, raw.splitlines())}, pattern)


def encoded(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, ids (array<int>) of every whole text."""
    return _run(docs, path, pattern, "doc_id long, ids array<int>", lambda ids, e: [pa.array([np.frombuffer(x, "<u4").astype(np.int32) for x in ids], pa.list_(pa.int32()))])


def decoded(tokens: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, text of doc_id, ids; bytes that aren't UTF-8 become U+FFFD, a null list null."""
    shared = tokens.sparkSession.sparkContext.broadcast(_with_bounds(path, pattern))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = Encoder(_parsed(*shared.value))
        for b in batches:
            yield pa.RecordBatch.from_arrays([b[0], pa.array([None if x is None else e.decode(np.array(x, "<u4").tobytes()).decode("utf-8", "replace") for x in b[1].to_pylist()], pa.string())], ["doc_id", "text"])

    return tokens.select(F.col("doc_id").cast("long"), "ids").mapInArrow(run, "doc_id long, text string")


def digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every whole text, encoded and decoded again."""

    def columns(ids: list[bytes], e: Encoder) -> list[pa.Array]:
        return [
            pa.array([len(x) // 4 for x in ids], pa.int64()),
            pa.array([hashlib.sha256(x).hexdigest() for x in ids], pa.string()),
            pa.array([hashlib.sha256(e.decode(x)).hexdigest() for x in ids], pa.string()),
        ]

    return _run(docs, path, pattern, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", columns)


def _run(docs: DataFrame, path: str, pattern: str, schema: str, columns) -> DataFrame:
    # The file's size is a property of the vocabulary (about 1 MB), not of the data.
    shared = docs.sparkSession.sparkContext.broadcast(_with_bounds(path, pattern))
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = Encoder(_parsed(*shared.value))
        for b in batches:
            for start, end, _, _ in chunks(b[1], CHUNK_BYTES):
                texts = [t or "" for t in b[1].slice(start, end - start).to_pylist()]
                yield pa.RecordBatch.from_arrays([b[0].slice(start, end - start), *columns(e.encode(texts), e)], names)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema)


def public_vocabulary(spark: SparkSession | None = None) -> tuple[str, str]:
    """Path and pattern of the vocabulary that the queries use."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN
