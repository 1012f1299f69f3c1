"""GIF media: LZW code streams, palettes, disposal and transparency, timed frames and colour histograms.

`write_gif` stores 8-bit samples losslessly as palette indices; `read_gif` is a decoder for any GIF87a/89a stream:
local and global palettes, interlacing, graphic control (delay, transparency, disposal 0-3), sub-blocks of any cut.
Frames are rendered on the logical screen in turn, and each keeps its delay and a colour histogram.

Defined cases: a null text counts as empty; the payload is padded with zero bytes to a positive multiple of 64; long
payloads become several frames of at most ROWS rows each, so nothing is cut off; a broken stream raises ValueError in
`read_gif` and gives a null frame list in `frames`. Rows keep their multiplicity; only the named columns are read.
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

from . import _text as tx

WIDTH, ROWS, DELAY = 64, 1024, 10
BINS = 4  # for each of red, green and blue


@dataclass
class Frame:
    left: int
    top: int
    delay_cs: int
    disposal: int
    transparent: int | None
    indices: np.ndarray  # of the frame's own rectangle
    canvas: np.ndarray  # height x width x 3 as shown; only the frame's rectangle when asked for

    def histogram(self) -> np.ndarray:
        """Counts of the BINS**3 colour cells of what is shown."""
        cells = (self.canvas.reshape(-1, 3).astype(np.int64) * BINS) >> 8
        return np.bincount((cells[:, 0] * BINS + cells[:, 1]) * BINS + cells[:, 2], minlength=BINS**3)


def _widths(n: int, size: int) -> np.ndarray:
    """Bits of each of the first n codes after a clear code, when every code adds an entry."""
    entries = np.arange(n) + (1 << size) + 1  # entries when a code is read; the first code adds none
    bits = np.full(n, size + 1)
    for b in range(size + 1, 12):
        bits[entries >= (1 << b)] = b + 1
    return bits


def lzw_codes(samples: bytes) -> list[list[int]]:
    """Codes of 8-bit samples, in runs that each begin after a clear code."""
    runs, run, table, size = [], [], {}, 258
    get = table.get
    put = run.append
    prefix = samples[0]
    for byte in memoryview(samples)[1:]:
        key = (prefix << 8) | byte
        code = get(key)
        if code is not None:
            prefix = code
            continue
        put(prefix)
        if size < 4095:
            table[key] = size
            size += 1
        else:  # begin anew while a code still fits 12 bits
            runs.append(run)
            run, size = [], 258
            table.clear()
            put = run.append
        prefix = byte
    put(prefix)
    runs.append(run)
    return runs


def pack_codes(runs: list[list[int]]) -> bytes:
    """The bit stream with a clear code before each run and an end code at last."""
    values, places, at = [], [], 0
    for k, run in enumerate(runs):
        n = len(run)
        starts, w = _layout(0, 4096, 8)
        values += [[256], run]
        places += [[at], starts[:n] + (at + (last if k else 9))]
        at += (last if k else 9) + int(starts[n])
        last = int(w[n])  # bits of the code after the run
    values.append([257])
    places.append([at])
    v = np.concatenate(values).astype(np.uint32)
    p = np.concatenate(places).astype(np.int64)
    v <<= (p & 7).astype(np.uint32)
    p >>= 3
    out = np.zeros((at + last + 7) // 8 + 3, np.float64)  # bits never overlap, so sums are unions
    for k in range(3):
        out += np.bincount(p + k, ((v >> np.uint32(8 * k)) & np.uint32(255)), len(out))
    return out.astype(np.uint8)[: (at + last + 7) // 8].tobytes()


def write_gif(samples: bytes) -> bytes:
    """A grey-ramp GIF whose frames, one after the other, hold the samples; a positive multiple of WIDTH of them."""
    rows = len(samples) // WIDTH
    if not rows or len(samples) % WIDTH:
        raise ValueError("the samples must fill rows")
    out = [b"GIF89a", struct.pack("<HHBBB", WIDTH, min(rows, ROWS), 0xF7, 0, 0), bytes(np.repeat(np.arange(256, dtype=np.uint8), 3))]
    for top in range(0, rows, ROWS):
        high = min(ROWS, rows - top)
        out.append(b"\x21\xf9\x04" + struct.pack("<BHBB", 1 << 2, DELAY, 0, 0))
        out.append(b"\x2c" + struct.pack("<HHHHB", 0, 0, WIDTH, high, 0) + b"\x08")
        stream = pack_codes(lzw_codes(samples[top * WIDTH : (top + high) * WIDTH]))
        out += [bytes([len(block)]) + block for block in (stream[i : i + 255] for i in range(0, len(stream), 255))]
        out.append(b"\0")
    return b"".join(out) + b"\x3b"


def unpack_lzw(stream: bytes, size: int, want: int) -> bytes:
    """Samples of an LZW code stream whose minimum code size is `size`."""
    if not 1 <= size <= 11:
        raise ValueError("bad code size")
    clear, end = 1 << size, (1 << size) + 1
    first = clear + 2
    bits = np.unpackbits(np.frombuffer(stream, np.uint8), bitorder="little")
    bits = np.append(bits, np.zeros(12, np.uint8)).astype(np.int32)
    window = bits[:-11].copy()  # the twelve bits that begin at each place
    for k in range(1, 12):
        window += bits[k : len(bits) - 11 + k] << k
    total = len(bits) - 12
    out, got, at = [], 0, 0
    while at + size + 1 <= total and got < want:
        # until the next clear code, where a code lies depends on its number alone
        n, block, codes = 0, 4096, []
        while True:
            starts, w = _layout(n, block, size)
            starts = starts + at
            fit = int(np.searchsorted(starts + w, total, "right"))
            found = window[starts[:fit]] & ((1 << w[:fit]) - 1)
            stops = np.flatnonzero((found == clear) | (found == end))
            stop = int(stops[0]) if len(stops) else fit
            codes.append(found[:stop])
            if stop < fit:
                at = total if found[stop] == end else int(starts[stop] + w[stop])
                break
            if fit < block:
                at = total
                break
            n, at = n + block, int(starts[-1] + w[-1])
        part = _expand(np.concatenate(codes), clear, first)
        out.append(part)
        got += len(part)
    return b"".join(out)


_layouts: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}


def _layout(n: int, block: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Where codes n to n + block lie, from the place of the first of them, and their widths."""
    key = (min(n, 4096), size)  # all later codes have twelve bits
    if key not in _layouts:
        w = _widths(key[0] + block, size)[key[0] :]
        _layouts[key] = np.cumsum(w) - w, w
    return _layouts[key]


def _expand(codes: np.ndarray, clear: int, first: int) -> bytes:
    """The samples of the codes after one clear code.

    Entry first + i is what code i stands for and the sample after it, which directly follows in the output. So a
    code's length is one more than its parent's, and each sample is a copy of an earlier one: both are chains, which
    pointer doubling resolves without a loop over codes.
    """
    n = len(codes)
    if not n:
        return b""
    parent = np.where(codes < clear, -1, codes - first)
    if (parent >= np.arange(n)).any():
        raise ValueError("a code before its entry")
    length, up = np.ones(n + 1, np.int64), np.append(parent, -1)
    length[-1] = 0
    length[:-1][parent < 0] = 1
    while (up[:-1] >= 0).any():  # length counts the hops done so far
        length[:-1] += np.where(up[:-1] >= 0, length[up[:-1]], 0)
        up = np.where(up >= 0, up[up], -1)
    length = length[:-1]
    ends = np.cumsum(length)
    starts = ends - length
    total = int(ends[-1])
    source = np.arange(total)
    whole = parent >= 0
    shift = np.where(whole, starts - starts[np.maximum(parent, 0)], 0)
    source -= np.repeat(shift, length)
    while True:
        nxt = source[source]
        if np.array_equal(nxt, source):
            break
        source = nxt
    literal = np.zeros(total, np.uint8)
    literal[starts[~whole]] = codes[~whole]
    return literal[source].tobytes()


def read_gif(media: bytes, full_canvas: bool = True) -> list[Frame]:
    """All frames as shown. full_canvas=False keeps only each frame's rectangle of the canvas."""
    if media[:6] not in (b"GIF87a", b"GIF89a"):
        raise ValueError("no GIF")
    wide, high, flags, background, _ = struct.unpack_from("<HHBBB", media, 6)
    at, palette = 13, None
    if flags & 0x80:
        n = 2 << (flags & 7)
        palette = np.frombuffer(media, np.uint8, 3 * n, at).reshape(n, 3)
        at += 3 * n
    canvas = np.zeros((high, wide, 3), np.uint8)
    if palette is not None and background < len(palette):
        canvas[:] = palette[background]
    base = canvas.copy()
    frames: list[Frame] = []
    delay, disposal, transparent = 0, 0, None

    def blocks(at: int) -> tuple[bytes, int]:
        parts = []
        while media[at]:
            parts.append(media[at + 1 : at + 1 + media[at]])
            at += 1 + media[at]
        return b"".join(parts), at + 1

    try:
        while media[at] != 0x3B:
            if media[at] == 0x21:
                label = media[at + 1]
                body, at = blocks(at + 2)
                if label == 0xF9:
                    packed, delay, clear_index = struct.unpack("<BHB", body[:4])
                    disposal, transparent = packed >> 2 & 7, clear_index if packed & 1 else None
            elif media[at] == 0x2C:
                left, top, w, h, packed = struct.unpack_from("<HHHHB", media, at + 1)
                at += 10
                colours = palette
                if packed & 0x80:
                    n = 2 << (packed & 7)
                    colours = np.frombuffer(media, np.uint8, 3 * n, at).reshape(n, 3)
                    at += 3 * n
                if colours is None:
                    raise ValueError("no palette")
                size = media[at]
                stream, at = blocks(at + 1)
                raw = unpack_lzw(stream, size, w * h)
                if len(raw) < w * h:
                    raise ValueError("too few samples")
                indices = np.frombuffer(raw, np.uint8, w * h).reshape(h, w)
                if packed & 0x40:
                    order = [*range(0, h, 8), *range(4, h, 8), *range(2, h, 4), *range(1, h, 2)]
                    indices = indices[np.argsort(order)]
                lines, columns = min(h, max(high - top, 0)), min(w, max(wide - left, 0))
                area = (slice(top, top + lines), slice(left, left + columns))
                before = canvas[area].copy() if disposal == 3 else None
                shown = indices[:lines, :columns]
                if len(colours) < 256 and shown.size and shown.max() >= len(colours):
                    raise ValueError("an index beyond the palette")
                if transparent is None:
                    canvas[area] = colours[shown]
                else:
                    solid = shown != transparent
                    canvas[area][solid] = colours[shown[solid]]
                frames.append(Frame(left, top, delay, disposal, transparent, indices, canvas.copy() if full_canvas else canvas[area].copy()))
                if disposal == 2:
                    canvas[area] = base[area]
                elif disposal == 3:
                    canvas[area] = before
                delay, disposal, transparent = 0, 0, None
            else:
                raise ValueError("an unknown block")
    except (IndexError, struct.error) as e:
        raise ValueError("the stream ends early") from e
    return frames


def payload_of(text: bytes) -> bytes:
    return text + bytes(-len(text) % 64 if text else 64)


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The id column, n_bytes and the GIF of every text."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("body"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in tx.each_slice(batch.column(1)):
                raw = data.tobytes()
                media = [write_gif(payload_of(raw[a:b])) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0)[i:j], pa.array(np.diff(offsets), pa.int64()), pa.array(media, pa.binary())], ["id", "n_bytes", "media"])

    return rows.mapInArrow(run, f"id {rows.schema['id'].dataType.simpleString()}, n_bytes long, media binary").withColumnRenamed("id", id_col)


FRAMES = "array<struct<frame:int,start_cs:long,delay_cs:int,width:int,height:int,disposal:int,transparent:int,samples:binary,colour_histogram:array<long>>>"


def frames(media: DataFrame, id_col: str = "doc_id", media_col: str = "media", carry: list[str] | None = None) -> DataFrame:
    """Decode every GIF: the id column, carried columns, the media column and its timed frames (null where it is broken).

    `samples` are the red values as shown in the frame's rectangle; for a grey ramp they are the stored samples.
    """
    rows = media.select(F.col(id_col).alias("id"), *(carry or []), F.col(media_col).alias("media"))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields)
    names = ("frame", "start_cs", "delay_cs", "width", "height", "disposal", "transparent", "samples", "colour_histogram")
    kind = pa.list_(pa.struct(list(zip(names, (pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.list_(pa.int64())), strict=True))))

    def decoded(raw: bytes | None) -> list[dict] | None:
        try:
            found = read_gif(raw, full_canvas=False) if raw is not None else None
        except ValueError:
            return None
        out, clock = [], 0
        for k, f in enumerate(found or []):
            out.append(dict(zip(names, (k, clock, f.delay_cs, f.indices.shape[1], f.indices.shape[0], f.disposal, f.transparent, f.canvas[:, :, 0].tobytes(), f.histogram().tolist()), strict=True)))
            clock += f.delay_cs
        return out if found is not None else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(batch.num_columns - 1)
            for i in range(0, batch.num_rows, 64):
                part = batch.slice(i, 64)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array([decoded(x.as_py()) for x in column[i : i + 64]], kind)], [*batch.schema.names, "frames"])

    return rows.mapInArrow(run, f"{kinds}, frames {FRAMES}").withColumnRenamed("id", id_col)


def digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store every text, read it back, and digest both: the columns of the contract of op6, in one pass over Arrow batches."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("body"))
    names = ["id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "n_frames", "feature"]

    def one(text: bytes) -> tuple:
        media = write_gif(payload_of(text))
        shown = read_gif(media, full_canvas=False)
        back = b"".join(f.canvas[:, :, 0].tobytes() for f in shown)
        counts = sum((f.histogram() for f in shown), np.zeros(BINS**3, np.int64))
        feature = f"{len(shown)}x{sum(f.delay_cs for f in shown)}:" + ",".join(f"{i}={c}" for i, c in enumerate(counts.tolist()) if c)
        return len(text), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), len(shown), feature

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int32(), pa.string()]
        for batch in batches:
            for i, j, data, offsets in tx.each_slice(batch.column(1)):
                raw = data.tobytes()
                made = [one(raw[a:b]) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0)[i:j], *(pa.array(x, k) for x, k in zip(zip(*made, strict=True), kinds, strict=True))], names)

    return rows.mapInArrow(run, f"id {rows.schema['id'].dataType.simpleString()}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, n_frames int, feature string").withColumnRenamed("id", id_col)
