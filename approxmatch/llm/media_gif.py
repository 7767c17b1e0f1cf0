"""GIF media columns: byte payloads as indexed frames, and a decoder for any GIF of the 1989 format.

Writing: the samples fill rows of 64 pixels of a 256-colour image whose palette is grey level i at index i;
frames are at most 1,024 rows high, stand at the same place, carry 10/100 s and leave the canvas alone (disposal 1).
Code streams are LZW with 9 to 12 bits and a clear code when the dictionary is full.

Reading: header, global and local palettes, graphic control extensions (delay, disposal, transparency), image
descriptors with or without interlacing, LZW code streams, other extensions skipped. `composite` applies the
disposal rules 0-3 and transparency and yields the canvas of each timed frame.

Defined cases: a null text is empty; any payload gets zero bytes up to a positive multiple of 64, so that an empty
text is one row of zeros; equal texts and repeated rows give equal bytes; long texts give more frames; `decode` raises
ValueError naming the reason for any broken stream, and `media_frames` gives such a GIF one row with that reason; null
media give no row; an empty table gives an empty result; further columns are not read, whatever their names.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WIDTH = 64
ROWS_A_FRAME = 1024
DELAY = 10
_GREY = bytes(v for i in range(256) for v in (i, i, i))


def padded(data: bytes) -> bytes:
    return data + b"\0" * (WIDTH - len(data) % WIDTH if len(data) % WIDTH or not data else 0)


# ---- LZW ------------------------------------------------------------------------------------------------


def _pack(codes: np.ndarray, widths: np.ndarray) -> bytes:
    """Codes of 12 bits at most, least significant bit first."""
    at = np.zeros(len(codes), np.int64)
    np.cumsum(widths[:-1], out=at[1:])
    size = int(at[-1] + widths[-1] + 7) // 8
    spread = codes.astype(np.int64) << (at & 7)
    out = np.zeros(size + 3, np.int64)
    first = at >> 3
    for k in range(3):  # codes begin at different bits, so adding is the same as or-ing
        out[: size + 3] += np.bincount(first + k, (spread >> (8 * k)) & 255, size + 3).astype(np.int64)
    return out[:size].astype(np.uint8).tobytes()


def lzw_encode(data: bytes, bits: int = 8) -> bytes:
    """The code stream of samples below 2**bits, clear code first and end code last."""
    clear = 1 << bits
    codes, cuts = [clear], [1]  # cuts: how many codes before each restart of the dictionary
    put, n = codes.append, len(data)
    table: dict[int, int] = {}
    find, free, prefix = table.get, clear + 2, -1
    if n:
        prefix = data[0]
    for sample in memoryview(data)[1:]:
        key = prefix << 8 | sample
        longer = find(key)
        if longer is not None:
            prefix = longer
            continue
        put(prefix)
        prefix = sample
        if free < 4096:
            table[key] = free
            free += 1
        else:
            put(clear)
            cuts.append(len(codes))
            table.clear()
            free = clear + 2
    if prefix >= 0:
        put(prefix)
    put(clear + 1)
    return _pack(np.array(codes, np.int64), _widths(len(codes), np.array(cuts), bits))


def _widths(n: int, cuts: np.ndarray, bits: int) -> np.ndarray:
    """Bits of each code: k codes after a clear code the decoder has k - 1 new entries, at most up to 12 bits."""
    since = np.arange(n) - np.repeat(np.concatenate([[0], cuts]), np.diff(np.concatenate([[0], cuts, [n]])))
    entries = (1 << bits) + 2 + np.maximum(since - 1, 0)
    widths = np.minimum(np.floor(np.log2(np.maximum(entries, 1))).astype(np.int64) + 1, 12)
    widths[0] = bits + 1
    return widths


def _codes(stream: bytes, bits: int) -> Iterator[int]:
    """Codes as they stand, with the width growing as the decoder's dictionary does."""
    clear, end = 1 << bits, (1 << bits) + 1
    raw = np.unpackbits(np.frombuffer(stream, np.uint8), bitorder="little")
    at, total = 0, len(raw)
    while at < total:
        # Between two clear codes the widths are known beforehand; unpack that stretch at once.
        free, width, block, start = clear + 2, bits + 1, [], at
        while True:
            room = (1 << width) - free + 1 if width < 12 else 4096
            room = min(room, (total - start) // width)
            if room <= 0:
                break
            values = raw[start : start + room * width].reshape(room, width).astype(np.int32) @ (1 << np.arange(width, dtype=np.int32))
            stop = np.flatnonzero(values == clear)
            over = np.flatnonzero(values == end)
            if len(over) and (not len(stop) or over[0] < stop[0]):
                block.append(values[: over[0] + 1])
                start += (int(over[0]) + 1) * width
                yield from np.concatenate(block).tolist()
                return
            if len(stop):
                block.append(values[: stop[0] + 1])
                start += (int(stop[0]) + 1) * width
                break
            block.append(values)
            start += room * width
            free += room
            if width < 12:
                width += 1
            elif room < 4096 and (total - start) // width <= 0:
                break
        if not block:
            return
        yield from np.concatenate(block).tolist()
        if start == at:
            return
        at = start


def lzw_decode(stream: bytes, bits: int, expected: int) -> bytes:
    """The samples of a code stream; ValueError where it refers to what isn't there."""
    clear, end = 1 << bits, (1 << bits) + 1
    single = [bytes([i]) for i in range(clear)] + [b"", b""]
    table, before, out = single.copy(), b"", []
    put = out.append
    grow = table.append
    size = len(table)
    for code in _codes(stream, bits):
        if code < size:
            if code >= clear and code <= end:
                if code == end:
                    break
                table = single.copy()
                grow, size, before = table.append, clear + 2, b""
                continue
            word = table[code]
            if before and size < 4096:
                grow(before + word[:1])
                size += 1
        elif code == size and before and size < 4096:
            word = before + before[:1]
            grow(word)
            size += 1
        else:
            raise ValueError("a code refers to no entry")
        put(word)
        before = word
    samples = b"".join(out)
    if len(samples) < expected:
        raise ValueError(f"{len(samples)} samples where the image has {expected}")
    return samples[:expected]


# ---- container ------------------------------------------------------------------------------------------


def _sub_blocks(data: bytes) -> bytes:
    parts = []
    for i in range(0, len(data), 255):
        piece = data[i : i + 255]
        parts += (bytes([len(piece)]), piece)
    return b"".join(parts) + b"\0"


def encode(payload: bytes) -> bytes:
    """A GIF that holds the payload, a positive multiple of 64 bytes, as its samples."""
    if not payload or len(payload) % WIDTH:
        raise ValueError("the payload isn't a positive multiple of 64 bytes")
    rows = len(payload) // WIDTH
    out = [b"GIF89a", struct.pack("<HHBBB", WIDTH, min(rows, ROWS_A_FRAME), 0xF7, 0, 0), _GREY]
    for top in range(0, rows, ROWS_A_FRAME):
        high = min(ROWS_A_FRAME, rows - top)
        out += (b"\x21\xf9\x04", struct.pack("<BHB", 1 << 2, DELAY, 0), b"\0")
        out += (b"\x2c", struct.pack("<HHHHB", 0, 0, WIDTH, high, 0), b"\x08")
        out.append(_sub_blocks(lzw_encode(payload[top * WIDTH : (top + high) * WIDTH])))
    out.append(b"\x3b")
    return b"".join(out)


@dataclass
class Frame:
    left: int
    top: int
    width: int
    height: int
    samples: bytes
    palette: np.ndarray
    delay: int
    disposal: int
    transparent: int | None


@dataclass
class Image:
    width: int
    height: int
    background: int
    palette: np.ndarray | None
    frames: list[Frame]


def _table(data: bytes, at: int, flags: int) -> tuple[np.ndarray, int]:
    n = 2 << (flags & 7)
    if at + 3 * n > len(data):
        raise ValueError("the palette is cut off")
    return np.frombuffer(data, np.uint8, 3 * n, at).reshape(n, 3), at + 3 * n


def _blocks(data: bytes, at: int) -> tuple[bytes, int]:
    parts = []
    while True:
        if at >= len(data):
            raise ValueError("a block is cut off")
        n = data[at]
        if not n:
            return b"".join(parts), at + 1
        parts.append(data[at + 1 : at + 1 + n])
        at += 1 + n


def _deinterlaced(samples: bytes, width: int, height: int) -> bytes:
    lines = [y for first, step in ((0, 8), (4, 8), (2, 4), (1, 2)) for y in range(first, height, step)]
    out = np.empty((height, width), np.uint8)
    out[lines] = np.frombuffer(samples, np.uint8).reshape(height, width)
    return out.tobytes()


def decode(data: bytes) -> Image:
    try:
        return _decode(data)
    except (IndexError, struct.error) as e:
        raise ValueError("the stream is cut off") from e


def _decode(data: bytes) -> Image:
    if data[:6] not in (b"GIF87a", b"GIF89a"):
        raise ValueError("no GIF header")
    width, height, flags, background, _ = struct.unpack_from("<HHBBB", data, 6)
    at, palette = 13, None
    if flags & 0x80:
        palette, at = _table(data, at, flags)
    image, control = Image(width, height, background, palette, []), (0, 0, None)
    while True:
        kind = data[at] if at < len(data) else None
        if kind == 0x3B:
            return image
        if kind == 0x21:
            label, (body, at) = data[at + 1], _blocks(data, at + 2)
            if label == 0xF9 and len(body) >= 4:
                bits, delay, index = struct.unpack_from("<BHB", body)
                control = (delay, bits >> 2 & 7, index if bits & 1 else None)
        elif kind == 0x2C:
            left, top, w, h, bits = struct.unpack_from("<HHHHB", data, at + 1)
            at += 10
            own = image.palette
            if bits & 0x80:
                own, at = _table(data, at, bits)
            if own is None:
                raise ValueError("a frame has no palette")
            stream, end = _blocks(data, at + 1)
            if not 1 <= data[at] <= 8:
                raise ValueError(f"{data[at]} bits a code can't be")
            samples, at = lzw_decode(stream, data[at], w * h), end
            if bits & 0x40:
                samples = _deinterlaced(samples, w, h)
            image.frames.append(Frame(left, top, w, h, samples, own, *control))
            control = (0, 0, None)
        else:
            raise ValueError("neither extension, image nor end")


def composite(image: Image) -> Iterator[tuple[int, np.ndarray]]:
    """(delay in 1/100 s, RGBA canvas) of each frame, under the disposal and transparency rules."""
    canvas = np.zeros((image.height, image.width, 4), np.uint8)
    for f in image.frames:
        saved = canvas.copy() if f.disposal == 3 else None
        box = (slice(f.top, min(f.top + f.height, image.height)), slice(f.left, min(f.left + f.width, image.width)))
        index = np.frombuffer(f.samples, np.uint8).reshape(f.height, f.width)[: box[0].stop - f.top, : box[1].stop - f.left]
        table = np.zeros((256, 4), np.uint8)
        table[: len(f.palette), :3] = f.palette
        table[:, 3] = 255
        if f.transparent is None:
            canvas[box] = table[index]
        else:
            shown = index != f.transparent
            canvas[box][shown] = table[index[shown]]
        yield f.delay, canvas
        if f.disposal == 2:
            canvas[box] = 0
        elif saved is not None:
            canvas = saved


def colour_histogram(canvas: np.ndarray, bins: int = 8) -> np.ndarray:
    """Counts of opaque pixels by level of red, green and blue, bins each."""
    seen = canvas[canvas[..., 3] > 0]
    return np.stack([np.bincount(seen[:, c] >> 5 if bins == 8 else seen[:, c].astype(np.int64) * bins // 256, minlength=bins) for c in range(3)])


def frame_rows(data: bytes) -> list[dict]:
    """What is stored of each timed frame."""
    out, start = [], 0
    for k, (delay, canvas) in enumerate(composite(decode(data))):
        out.append({"frame": k, "start_cs": start, "delay_cs": delay, "histogram": colour_histogram(canvas).ravel().tolist()})
        start += delay
    return out


def media_frames(media: DataFrame, id_column: str = "doc_id", gif_column: str = "media") -> DataFrame:
    """A GIF column as timed frames: id, frame, start_cs, delay_cs, histogram (8 levels of red, green, blue), error. A
    broken GIF is one row with the error alone."""
    schema = pa.schema([(id_column, pa.int64()), ("frame", pa.int32()), ("start_cs", pa.int64()), ("delay_cs", pa.int64()), ("histogram", pa.list_(pa.int64())), ("error", pa.string())])

    def rows_of(data: bytes) -> list[dict]:
        try:
            return [x | {"error": None} for x in frame_rows(data)]
        except ValueError as e:
            return [{"frame": None, "start_cs": None, "delay_cs": None, "histogram": None, "error": str(e)}]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [{id_column: i} | x for i, data in zip(b[0].to_pylist(), b[1].to_pylist(), strict=True) if data is not None for x in rows_of(data)]
            if rows:
                yield pa.RecordBatch.from_pylist(rows, schema)

    return media.select(F.col(id_column).cast("long"), gif_column).mapInArrow(run, f"{id_column} long, frame int, start_cs long, delay_cs long, histogram array<long>, error string")


def store_texts(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media (the GIF)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 64):
                part = b.slice(i, 64)
                texts = [(t or "").encode() for t in part[1].to_pylist()]
                yield pa.RecordBatch.from_arrays([part[0], pa.array([len(t) for t in texts], pa.int64()), pa.array([encode(padded(t)) for t in texts], pa.binary())], ["doc_id", "n_bytes", "media"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n_bytes long, media binary")


def read_back(stored: DataFrame) -> DataFrame:
    """The digest of stored media: samples decoded, frames composed and stored with their times and histograms (8 levels
    of red, green, blue), the feature being their sum over time."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_frames int, duration_cs long, frames array<struct<start_cs:long,delay_cs:long,histogram:array<long>>>"
    names = [x.split()[0] for x in schema.split(", ")]
    frame = pa.struct([("start_cs", pa.int64()), ("delay_cs", pa.int64()), ("histogram", pa.list_(pa.int64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for n, data in zip(b[1].to_pylist(), b[2].to_pylist(), strict=True):
                image = decode(data)
                payload = b"".join(f.samples for f in image.frames)
                total, duration, frames = np.zeros((3, 8), np.int64), 0, []
                for delay, canvas in composite(image):
                    seen = colour_histogram(canvas)
                    frames.append({"start_cs": duration, "delay_cs": delay, "histogram": seen.ravel()})
                    total += seen
                    duration += delay
                feature = f"frames={len(image.frames)};cs={duration};hist=" + "/".join(",".join(map(str, row)) for row in total.tolist())
                rows.append((n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-WIDTH:]), len(data), hashlib.sha256(data).hexdigest(), feature, len(image.frames), duration, frames))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int64(), pa.list_(frame)]
            columns = list(zip(*rows, strict=True)) if rows else [[]] * len(kinds)
            yield pa.RecordBatch.from_arrays([b[0], *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names)

    return stored.mapInArrow(run, schema)


def text_media(docs: DataFrame) -> DataFrame:
    """Every text stored as GIF and read back: one row per document."""
    return read_back(store_texts(docs))
