"""What several corpus operators need: intermediate tables, let-bindings, and word scanning over Arrow buffers.

Words everywhere are maximal runs of bytes other than 0x20 and 0x09-0x0D. In UTF-8 those six bytes never
occur inside a longer character, so the scan works on bytes and never decodes.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed: the word and blank patterns, as Java and as DuckDB read them.
WORD = r"[^\x20\x09-\x0D]+"
BLANK = r"[\x20\x09-\x0D]+"

#: Bytes of text that the numpy scans hold at once; a longer document is a chunk of its own.
CHUNK_BYTES = 2_000_000


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; a temporary one only where that is unset and the master is local."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="shared-")
        spark.sparkContext.setCheckpointDir(found)
    return found


_written: list[tuple[SparkSession, str]] = []
#: Tables of the innermost `scratch`, in the order of writing.
_scope: ContextVar[list[tuple[SparkSession, str]]] = ContextVar("tables", default=_written)


def _delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


@contextmanager
def scratch() -> Iterator[None]:
    """Tables that are kept within are deleted at the end: no frame that reads one may leave."""
    own: list[tuple[SparkSession, str]] = []
    token = _scope.set(own)
    try:
        yield
    finally:
        _scope.reset(token)
        for spark, path in own:
            _delete(spark, path)


def alone(make: Callable[[], DataFrame]) -> DataFrame:
    """make(), kept; what was kept on the way is deleted."""
    with scratch():
        out = keep(make())
        done = _scope.get().pop()
    _scope.get().append(done)
    return out


def keep(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it again: the lineage ends there, so a lost executor costs
    no recomputation and every reader sees the same rows."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/tables/{uuid.uuid4().hex}"
    df.write.parquet(path)
    _scope.get().append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        try:
            _delete(spark, path)
        except Exception:  # noqa: BLE001  the session may be gone at exit; the folder is temporary anyway
            return


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value computed once: a lambda variable, which the optimiser can't inline again."""
    return F.transform(F.array(value), body)[0]


def word_count(text: Column) -> Column:
    """Words of a text, long; 0 for null. A word starts where a non-blank follows a blank or the start."""
    return F.coalesce(F.size(F.regexp_extract_all(text, F.lit(WORD), F.lit(0))), F.lit(0)).cast("long")


# ---- numpy side -----------------------------------------------------------------------------------------

U = np.uint64


def mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64, on uint64 with wrap-around."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def seeds(n: int, at: int) -> np.ndarray:
    """n pseudo-random uint64, by rule."""
    with np.errstate(over="ignore"):
        return mix((np.arange(1, n + 1, dtype=U) + U(at)) * U(0x9E3779B97F4A7C15))


_DELIM = np.zeros(256, bool)
_DELIM[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BYTE = seeds(256, 1000)
_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: list[np.ndarray] = []


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers[0]) < n:
        size = 1 << max(16, (n - 1).bit_length())
        _powers[:] = [np.cumprod(np.concatenate([[U(1)], np.full(size - 1, b, U)]), dtype=U) for b in (_BASE, _BASE_INVERSE)]
    return _powers[0], _powers[1]


def string_parts(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (from 0) of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, at, data = column.buffers()
    if len(column) == 0 or at is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    at = np.frombuffer(at, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None else np.zeros(0, np.uint8)
    return data, at - at[0]


def chunks(column: pa.Array, most: int = CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of consecutive rows with about `most` bytes together."""
    data, at = string_parts(column)
    row, n = 0, len(at) - 1
    while row < n:
        end = max(row + 1, int(np.searchsorted(at, at[row] + most, "right")) - 1)
        yield row, end, data[at[row] : at[end]], at[row : end + 1] - at[row]
        row = end


def lowered(data: np.ndarray) -> np.ndarray:
    return _LOWER[data]


def word_bytes(data: np.ndarray) -> np.ndarray:
    return ~_DELIM[data]


def word_spans(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and row of each word, in order. A row's end also ends its last word."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, none
    inside = word_bytes(data)
    edge = np.zeros(len(data) + 1, bool)
    edge[at] = True
    before = np.concatenate([[False], inside[:-1]])
    after = np.concatenate([inside[1:], [False]])
    starts = np.flatnonzero(inside & (~before | edge[:-1]))
    ends = np.flatnonzero(inside & (~after | edge[1:])) + 1
    return starts, ends, np.searchsorted(at, starts, "right") - 1


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of bytes, equal for equal bytes wherever they stand."""
    if not len(starts):
        return np.zeros(0, U)
    up, down = _power(len(data) + 1)
    sums = np.zeros(len(data) + 1, U)
    np.cumsum(_BYTE[data] * up[: len(data)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(U) * U(0xD6E8FEB86659FD93))


class KeyTable:
    """Positions of uint64 keys, by open addressing on whole vectors; at most a quarter of the slots are in use."""

    def __init__(self, keys: np.ndarray):
        self.bits = max(4, int(len(keys) * 4).bit_length())
        size = 1 << self.bits
        self.slots = np.full(size, -1, np.int32)
        self.keys = np.ascontiguousarray(keys, dtype=U)
        left, at = np.arange(len(keys), dtype=np.int32), self._home(self.keys)
        while len(left):
            empty = self.slots[at] < 0
            self.slots[at[empty]] = left[empty]  # of several, one stays
            go = self.slots[at] != left
            left, at = left[go], (at[go] + 1) & (size - 1)

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * U(0x9E3779B97F4A7C15)) >> U(64 - self.bits)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The position of each key, -1 without one."""
        if not len(self.keys):
            return np.full(len(keys), -1, np.int32)
        at = self._home(keys)
        out = self.slots[at]
        wrong = np.flatnonzero((out >= 0) & (self.keys[out] != keys))
        at = at[wrong]
        while len(wrong):
            at = (at + 1) & ((1 << self.bits) - 1)
            got = self.slots[at]
            out[wrong] = got
            go = (got >= 0) & (self.keys[got] != keys[wrong])
            wrong, at = wrong[go], at[go]
        return out


class Tally:
    """Counts of uint64 keys within a task; memory follows the different keys."""

    def __init__(self, most: int = 1_500_000):
        self.keys, self.counts = np.zeros(0, U), np.zeros(0, np.int64)
        self.waiting: list[np.ndarray] = []
        self.held, self.most = 0, most

    def add(self, keys: np.ndarray) -> None:
        self.waiting.append(keys)
        self.held += len(keys)
        if self.held >= self.most:
            self.settle()

    def settle(self) -> None:
        if self.held:
            every = np.sort(np.concatenate(self.waiting))
            first = np.flatnonzero(np.concatenate([[True], every[1:] != every[:-1]]))
            k, n = every[first], np.diff(np.append(first, len(every)))
            self.waiting, self.held = [], 0
            if len(self.keys):
                # both are sorted: known keys gain, new ones are put between
                at = np.searchsorted(self.keys, k)
                known = self.keys[np.minimum(at, len(self.keys) - 1)] == k
                self.counts[at[known]] += n[known]
                k, n = np.insert(self.keys, at[~known], k[~known]), np.insert(self.counts, at[~known], n[~known])
            self.keys, self.counts = k, n

    def cleared(self) -> tuple[np.ndarray, np.ndarray]:
        """Keys and counts so far; the tally begins anew."""
        self.settle()
        out = self.keys, self.counts
        self.keys, self.counts = np.zeros(0, U), np.zeros(0, np.int64)
        return out

    def batches(self, names: tuple[str, str] = ("k", "n"), most: int = 100_000) -> Iterator[pa.RecordBatch]:
        self.settle()
        for i in range(0, len(self.keys), most):
            yield pa.RecordBatch.from_arrays([pa.array(self.keys[i : i + most].view(np.int64)), pa.array(self.counts[i : i + most])], list(names))
