"""GIF media columns: LZW code streams, palettes, disposal and transparency, timed frames, histograms.

``encode`` writes a GIF89a of indexed frames with a real growing LZW table; ``decode`` reads any
GIF87a/89a: global and local palettes, interlacing, graphic control, all four disposal methods and
transparency, deferred clear codes, truncated streams.

The decoder is vectorised. Between two clear codes the width of the k-th code depends on k alone,
so all codes of a stretch are unpacked at once; an entry of the table is always a stretch of the
output already written, so lengths and bytes are found by following such references with pointer
doubling instead of byte by byte.

Defined results: null text counts as empty (64 zero bytes of payload); repeated rows are each
stored; broken files give the frames before the fault, and a value without a GIF header none.
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
from pyspark.sql.types import ArrayType, LongType, StructField, StructType

from cubegrid.llm.common import fresh, slices, stored, tame_arrow

TABLE_FULL = 4096
GREY = np.repeat(np.arange(256, dtype=np.uint8)[:, None], 3, axis=1)
#: Payload layout: frames of 64 columns and at most so many rows.
COLUMNS, ROWS = 64, 1024


@dataclass
class Frame:
    left: int
    top: int
    indices: np.ndarray  # rows x columns
    delay: int = 0  # hundredths of a second
    disposal: int = 0
    transparent: int = -1
    palette: np.ndarray | None = None
    canvas: np.ndarray | None = None  # rows x columns x RGBA after this frame is drawn


def _widths(bits: int) -> np.ndarray:
    """Width of the k-th code after a clear code, for a table that starts with 2^bits + 2 entries."""
    free = (1 << bits) + 2
    k = np.arange(TABLE_FULL - free + 1, dtype=np.int32)
    before = free + np.maximum(k - 1, 0)
    width = np.maximum(bits + 1, np.floor(np.log2(before)).astype(np.int32) + 1)
    return np.minimum(width, 12)


_WIDTHS = {b: _widths(b) for b in range(2, 9)}
#: Which of 16 bits of the k-th code are written.
_MASKS = {b: np.arange(16) < np.append(w, [12, 12])[:, None] for b, w in _WIDTHS.items()}


# ---- LZW ----------------------------------------------------------------------------------------


def lzw_encode(data: bytes, bits: int = 8) -> bytes:
    clear, end, free = 1 << bits, (1 << bits) + 1, (1 << bits) + 2
    runs: list[list[int]] = []
    codes = [clear << 8]
    if data:
        # codes are held shifted by a byte, so that a key is one "or" away
        table: dict[int, int] = {}
        put = codes.append
        current, new, full = data[0] << 8, free << 8, TABLE_FULL << 8
        for byte in data[1:]:
            key = current | byte
            if key in table:
                current = table[key]
                continue
            put(current)
            table[key] = new
            current = byte << 8
            new += 256
            if new == full:
                put(clear << 8)
                runs.append(codes)
                codes = []
                put = codes.append
                table.clear()
                new = free << 8
        put(current)
    codes.append(end << 8)
    runs.append(codes)
    parts, masks = [], []
    for i, run in enumerate(runs):
        lead = 1 if i == 0 else 0  # the first clear code has the first width
        parts.append(np.asarray(run, np.int32))
        if lead:
            masks.append(_MASKS[bits][:1])
        masks.append(_MASKS[bits][: len(run) - lead])
    code = (np.concatenate(parts) >> 8).astype("<u2")
    out = np.unpackbits(code.view(np.uint8), bitorder="little").reshape(-1, 16)[np.concatenate(masks)]
    return np.packbits(out, bitorder="little").tobytes()


def lzw_decode(stream: bytes, bits: int, expected: int) -> np.ndarray:
    """At most ``expected`` indices; shorter where the stream ends or breaks."""
    clear, end, free = 1 << bits, (1 << bits) + 1, (1 << bits) + 2
    widths = _WIDTHS[bits]
    total = 8 * len(stream)
    raw = np.frombuffer(stream + b"\0\0\0", np.uint8)
    out: list[np.ndarray] = []
    made = 0
    at = 0
    while made < expected:
        codes: list[np.ndarray] = []
        k, stop = 0, False
        while True:
            n = min((total - at) // (bits + 1), len(widths) if k == 0 else TABLE_FULL)
            if n <= 0:
                stop = True
                break
            size = widths[:n] if k == 0 else np.full(n, 12, np.int32)
            ends = np.cumsum(size, dtype=np.int32)
            ends = ends[ends <= total - at]
            if not len(ends):
                stop = True
                break
            size = size[: len(ends)]
            pos = (at & 7) + ends - size
            byte = pos >> 3
            window = raw[at >> 3 :]
            word = window[byte].astype(np.int32) | window[byte + 1].astype(np.int32) << 8 | window[byte + 2].astype(np.int32) << 16
            code = (word >> (pos & 7)) & ((1 << size) - 1)
            special = np.flatnonzero((code == clear) | (code == end))
            if len(special):
                first = special[0]
                stop = code[first] == end
                at += int(ends[first])
                codes.append(code[:first])
                break
            codes.append(code)
            at += int(ends[-1])
            k += len(code)
        stretch = np.concatenate(codes) if codes else np.zeros(0, np.int32)
        piece, whole = _expand(stretch, clear, free)
        out.append(piece)
        made += len(piece)
        if stop or not whole:
            break
    got = np.concatenate(out) if out else np.zeros(0, np.uint8)
    return got[:expected]


def _expand(code: np.ndarray, clear: int, free: int) -> tuple[np.ndarray, bool]:
    """Bytes of the codes between two clear codes; False if a code names an entry not yet made."""
    n = len(code)
    if not n:
        return np.zeros(0, np.uint8), True
    entry = code - free  # entry e stands for the bytes of code e and the first byte of code e + 1
    literal = code < clear
    bad = np.flatnonzero(~literal & (entry >= np.arange(n)))
    if len(bad):
        n = int(bad[0])
        code, entry, literal = code[:n], entry[:n], literal[:n]
        if not n:
            return np.zeros(0, np.uint8), False
    parent = np.where(literal, np.arange(n, dtype=np.int32), entry)
    depth = (~literal).astype(np.int32)
    jump = parent
    while True:
        further = jump[jump]
        depth += depth[jump]
        if np.array_equal(further, jump):
            break
        jump = further
    size = depth + 1
    start = np.zeros(n, np.int32)
    np.cumsum(size[:-1], out=start[1:], dtype=np.int32)
    source = np.arange(int(start[-1] + size[-1]), dtype=np.int32)
    source += np.repeat(start[parent] - start, size)
    while True:
        further = source[source]
        if np.array_equal(further, source):
            break
        source = further
    value = np.zeros(len(source), np.uint8)
    value[start[literal]] = code[literal]
    return value[source], not len(bad)


# ---- files --------------------------------------------------------------------------------------


def _blocks(data: bytes) -> bytes:
    return b"".join(bytes([len(data[i : i + 255])]) + data[i : i + 255] for i in range(0, len(data), 255)) + b"\0"


def encode(width: int, height: int, frames: list[Frame], palette: np.ndarray = GREY, loop: bool = False) -> bytes:
    bits = max(2, int(np.ceil(np.log2(max(4, len(palette))))))
    colours = np.zeros((1 << bits, 3), np.uint8)
    colours[: len(palette)] = palette
    out = [b"GIF89a", struct.pack("<HHBBB", width, height, 0x80 | (bits - 1) << 4 | (bits - 1), 0, 0), colours.tobytes()]
    if loop:
        out.append(b"\x21\xff\x0bNETSCAPE2.0\x03\x01\0\0\0")
    for f in frames:
        out.append(b"\x21\xf9\x04" + struct.pack("<BHBB", f.disposal << 2 | (f.transparent >= 0), f.delay, max(0, f.transparent), 0))
        rows, columns = f.indices.shape
        own = b""
        flags, local_bits = 0, bits
        if f.palette is not None:
            local_bits = max(2, int(np.ceil(np.log2(max(4, len(f.palette))))))
            local = np.zeros((1 << local_bits, 3), np.uint8)
            local[: len(f.palette)] = f.palette
            own, flags = local.tobytes(), 0x80 | (local_bits - 1)
        out.append(b"\x2c" + struct.pack("<HHHHB", f.left, f.top, columns, rows, flags) + own)
        out.append(bytes([local_bits]) + _blocks(lzw_encode(f.indices.tobytes(), local_bits)))
    return b"".join([*out, b"\x3b"])


def _sub_blocks(data: bytes, at: int) -> tuple[bytes, int]:
    parts = []
    while at < len(data) and (n := data[at]):
        parts.append(data[at + 1 : at + 1 + n])
        at += 1 + n
    return b"".join(parts), at + 1


def _palette(data: bytes, at: int, flags: int) -> tuple[np.ndarray | None, int]:
    if not flags & 0x80:
        return None, at
    n = 2 << (flags & 7)
    raw = data[at : at + 3 * n].ljust(3 * n, b"\0")
    return np.frombuffer(raw, np.uint8).reshape(n, 3), at + 3 * n


#: Pixels of the largest canvas or frame that is decoded: 128 MB of colours.
MOST_PIXELS = 1 << 25


def decode(data: bytes, compose: bool = True, most_pixels: int = MOST_PIXELS) -> Iterator[Frame]:
    """Frames in order, each with the canvas it leaves on screen while it is shown.

    What is no GIF gives none, nor does a canvas of more than ``most_pixels``; a damaged file, or a frame
    of more pixels, ends the frames.
    """
    if len(data) < 13 or data[:6] not in (b"GIF87a", b"GIF89a"):
        return
    width, height, flags = struct.unpack_from("<HHB", data, 6)
    if width * height > most_pixels:
        return
    shared, at = _palette(data, 13, flags)
    canvas = np.zeros((height, width, 4), np.uint8) if compose else None
    delay, disposal, transparent = 0, 0, -1
    try:
        while at < len(data):
            kind = data[at]
            if kind == 0x21:
                label = data[at + 1]
                body, at = _sub_blocks(data, at + 2)
                if label == 0xF9 and len(body) >= 4:
                    packed, delay, colour = struct.unpack_from("<BHB", body)
                    disposal, transparent = packed >> 2 & 7, colour if packed & 1 else -1
            elif kind == 0x2C:
                left, top, columns, rows, flags = struct.unpack_from("<HHHHB", data, at + 1)
                own, at = _palette(data, at + 10, flags)
                bits = data[at]
                body, at = _sub_blocks(data, at + 1)
                if not 2 <= bits <= 8 or rows * columns > most_pixels:
                    return
                flat = lzw_decode(body, bits, rows * columns)
                whole = len(flat) == rows * columns
                indices = np.zeros(rows * columns, np.uint8)
                indices[: len(flat)] = flat
                indices = indices.reshape(rows, columns)
                if flags & 0x40:
                    order = np.concatenate([np.arange(a, rows, s) for a, s in ((0, 8), (4, 8), (2, 4), (1, 2))])
                    straight = np.empty_like(indices)
                    straight[order] = indices
                    indices = straight
                frame = Frame(left, top, indices, delay, disposal, transparent, own if own is not None else shared)
                if canvas is not None:
                    canvas, frame.canvas = _draw(canvas, frame)
                yield frame
                delay, disposal, transparent = 0, 0, -1
                if not whole:
                    return
            else:
                return
    except (IndexError, struct.error):
        return


def _draw(canvas: np.ndarray, f: Frame) -> tuple[np.ndarray, np.ndarray]:
    """(canvas for the next frame, canvas shown with this one).

    A frame that is kept is drawn in place; its canvas is valid until the next frame is asked for.
    """
    shown = canvas if f.disposal < 2 and f.transparent < 0 else canvas.copy()
    bottom, right = min(f.top + f.indices.shape[0], canvas.shape[0]), min(f.left + f.indices.shape[1], canvas.shape[1])
    area = (slice(f.top, bottom), slice(f.left, right))
    part = f.indices[: max(0, bottom - f.top), : max(0, right - f.left)]
    palette = f.palette if f.palette is not None else GREY
    colours = np.full((256, 4), 255, np.uint8)
    colours[: len(palette), :3] = palette
    drawn = colours.view(np.uint32).ravel()[part].view(np.uint8).reshape(*part.shape, 4)
    if f.transparent >= 0:
        clear = part == f.transparent
        drawn[clear] = shown[area][clear]
    shown[area] = drawn
    if f.disposal == 2:
        after = shown.copy()
        after[area] = 0
        return after, shown
    if f.disposal == 3:
        return canvas, shown
    return shown, shown


def histogram(pixels: np.ndarray, bins: int = 8) -> np.ndarray:
    """Counts per channel and bin of RGB values: 3 x bins."""
    flat = pixels.reshape(-1, pixels.shape[-1])
    return np.stack([np.bincount(flat[:, c] * bins >> 8 if bins == 256 else flat[:, c] // (256 // bins), minlength=bins) for c in range(3)])


# ---- columns ------------------------------------------------------------------------------------


def payload_gif(payload: bytes) -> bytes:
    """Store bytes as grey frames of 64 columns, shown a tenth of a second each."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, COLUMNS)
    frames = [Frame(0, 0, rows[i : i + ROWS], 10, 1) for i in range(0, len(rows), ROWS)]
    return encode(COLUMNS, min(ROWS, len(rows)), frames)


def padded(text: bytes) -> bytes:
    return text + b"\0" * (max(64, -(-len(text) // 64) * 64) - len(text))


def encode_texts(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` plus n_bytes and media: the text's bytes, padded, as a GIF."""
    tame_arrow(docs.sparkSession)
    own = fresh(list(keep), "text")[0]
    narrow = docs.select(*[F.col(f"`{k}`") for k in keep], F.coalesce(F.col(text), F.lit("")).cast("binary").alias(own))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, own):
            rows = part.column(own).to_pylist()
            held = [part.column(i) for i in range(len(keep))]
            yield pa.RecordBatch.from_arrays([*held, pa.array([len(r) for r in rows], pa.int64()), pa.array([payload_gif(padded(r)) for r in rows], pa.binary())], names=[*keep, "n_bytes", "media"])

    return narrow.mapInArrow(run, narrow.drop(own).schema.add("n_bytes", "long").add("media", "binary"))


#: What is kept of a frame beside its 3 x 8 colour counts.
FRAME = ("frame", "start_ms", "delay_ms", "left", "top", "width", "height")


def timed_frames(data: bytes | None) -> Iterator[tuple[Frame, tuple[int, ...], np.ndarray]]:
    """Each frame with its number, start, delay, place and size, and the colour counts of what is shown."""
    start = 0
    for k, f in enumerate(decode(data or b"")):
        rows, columns = f.indices.shape
        yield f, (k, start, 10 * f.delay, f.left, f.top, columns, rows), histogram(f.canvas).ravel()
        start += 10 * f.delay


def _frame_columns(rows: list[tuple[int, ...]], hist: list[np.ndarray]) -> list[pa.Array]:
    return [*[pa.array([r[j] for r in rows], pa.int64()) for j in range(len(FRAME))], pa.array(hist, pa.list_(pa.int64()))]


def decode_frames(media: DataFrame, column: str = "media", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """One row per frame: number, start and delay in ms, place, size and 3 x 8 colour counts of what is shown."""
    tame_arrow(media.sparkSession)
    own = fresh(list(keep), "media")[0]
    narrow = media.select(*[F.col(f"`{k}`") for k in keep], F.col(column).alias(own))
    schema = narrow.drop(own).schema
    for n in FRAME:
        schema = schema.add(n, "long")
    schema = schema.add("histogram", ArrayType(LongType()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, own):
            at, rows, hist = [], [], []
            for i, data in enumerate(part.column(own).to_pylist()):
                for _, row, counts in timed_frames(data):
                    at.append(i)
                    rows.append(row)
                    hist.append(counts)
            held = part.select(list(keep)).take(pa.array(at, pa.int64()))
            yield pa.RecordBatch.from_arrays([*held.columns, *_frame_columns(rows, hist)], names=[*keep, *FRAME, "histogram"])

    return narrow.mapInArrow(run, schema)


def digest_media(media: DataFrame, keep: tuple[str, ...] = ("doc_id", "n_bytes"), column: str = "media") -> DataFrame:
    """What the stored bytes give when read back through palettes and canvas: payload size and digests,
    media digest, counts of the samples' upper four bits as feature, and the timed frames themselves."""
    tame_arrow(media.sparkSession)
    own = fresh(list(keep), "media")[0]
    narrow = media.select(*[F.col(f"`{k}`") for k in keep], F.col(column).alias(own))
    schema = narrow.drop(own).schema
    for n, kind in (("payload_bytes", "long"), ("payload_sha256", "string"), ("tail_crc32", "long"), ("media_bytes", "long"), ("media_sha256", "string"), ("feature", "string")):
        schema = schema.add(n, kind)
    one = StructType([*[StructField(n, LongType()) for n in FRAME], StructField("histogram", ArrayType(LongType()))])
    schema = schema.add("frames", ArrayType(one))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, own):
            rows, shown, hist, ends = [], [], [], [0]
            for data in part.column(own).to_pylist():
                data = data or b""
                parts, feature = [], np.zeros(16, np.int64)
                for f, row, counts in timed_frames(data):
                    high, wide = f.indices.shape
                    samples = np.ascontiguousarray(f.canvas[f.top : f.top + high, f.left : f.left + wide, 0])
                    parts.append(samples.tobytes())
                    feature += np.bincount(samples.ravel() >> 4, minlength=16)
                    shown.append(row)
                    hist.append(counts)
                ends.append(len(shown))
                payload = b"".join(parts)
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(data), hashlib.sha256(data).hexdigest(), ",".join(map(str, feature.tolist()))))
            held = [part.column(i) for i in range(len(keep))]
            new = [pa.array([r[j] for r in rows], pa.string() if j in (1, 4, 5) else pa.int64()) for j in range(6)]
            frames = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.StructArray.from_arrays(_frame_columns(shown, hist), names=[*FRAME, "histogram"]))
            yield pa.RecordBatch.from_arrays([*held, *new, frames], names=[*schema.names])

    return narrow.mapInArrow(run, schema)


def op6_gif_media(spark, sf_dir: str) -> DataFrame:
    """Every text stored as a GIF and read back: sizes, digests, a colour feature and the timed frames."""
    from cubegrid.llm.common import table

    media = stored(encode_texts(table(spark, sf_dir, "documents")), "gif-media")
    return digest_media(media)
