"""GIF as a media column: LZW code streams, palettes, disposal, transparency, timed frames.

``encode_payload`` stores bytes losslessly as the colour indices of GIF frames
(grey palette of 256, ``WIDTH`` samples a row, at most ``ROWS`` rows a frame).
``decode`` reads any GIF: it splits the blocks, unpacks and expands each
frame's LZW codes, undoes interlacing, and composes the canvas by palette,
transparency and disposal, giving timed frames.  Within a run between two clear
codes the width of the k-th code is a function of k alone, so codes are
unpacked from the bit stream a whole run at a time.

``media_features`` stores the timed frames of every row: delay, disposal and
the colour histogram of the composed canvas.  Colours are counted by the upper
four bits of red, green and blue; pixels that nothing has drawn have no colour.
Frames of a payload are cleared after their time, so each shows its own samples.

Defined results: a null text counts as empty and is stored as one row of
blanks; equal texts give equal bytes; damaged streams raise ``ValueError``;
an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entlink.storage import materialize

WIDTH, ROWS = 192, 192
DELAY = 4  # hundredths of a second for each frame
LEVELS = 16  # of each of red, green and blue
_GREY = bytes(v for i in range(256) for v in (i, i, i))


def _widths(min_bits: int) -> np.ndarray:
    """Bits of the k-th code after a clear code, for as many codes as fit the table."""
    first_free = (1 << min_bits) + 2
    # When the k-th code is read, the table has first_free + max(0, k - 1) entries.
    filled = first_free + np.maximum(0, np.arange(4096 - first_free + 1) - 1)
    return np.maximum(min_bits + 1, np.minimum(12, np.floor(np.log2(np.maximum(filled, 1))).astype(int) + 1))


_WIDTHS = {m: _widths(m) for m in range(2, 9)}


def lzw_encode(samples: bytes, min_bits: int = 8) -> bytes:
    """LZW code stream of samples; the table is cleared when it is full."""
    clear = 1 << min_bits
    runs, rest = [], iter(samples)
    codes: list[int] = []
    for s in rest:  # one turn for each table; codes stand shifted by a sample, so that a sample fits below
        table, free, prefix = {}, clear + 2 << 8, s << 8
        get, put = table.get, codes.append
        for s in rest:
            key = prefix | s
            found = get(key)
            if found is not None:
                prefix = found
                continue
            put(prefix)
            table[key] = free
            free += 256
            prefix = s << 8
            if free == 4096 << 8:
                break
        put(prefix)
        if free == 4096 << 8:
            put(clear << 8)
            runs.append(codes)
            codes = []
    codes.append(clear + 1 << 8)
    runs.append(codes)
    schedule = _WIDTHS[min_bits]
    widths = [np.array([min_bits + 1])]
    for r in runs:
        w = schedule[: len(r)]
        widths.append(np.concatenate((w, np.full(len(r) - len(w), 12))))
    values = np.concatenate([np.array([clear]), *[np.array(r) >> 8 for r in runs]]).astype(np.uint16)
    width = np.concatenate(widths)
    return _pack(values, width)


def _pack(values: np.ndarray, width: np.ndarray) -> bytes:
    """Codes of given widths, least bit first."""
    bits = np.unpackbits(values.view(np.uint8).reshape(-1, 2), axis=1, bitorder="little")
    return np.packbits(bits[np.arange(16) < width[:, None]], bitorder="little").tobytes()


def _codes(words: np.ndarray, at: int, ends: np.ndarray, width: np.ndarray) -> np.ndarray:
    """As many codes of the given widths, which end ``ends`` bits on, as the stream holds from bit ``at``; ``words`` has the 24 bits from each byte on."""
    n = int(np.searchsorted(ends, 8 * len(words) - at, side="right"))
    starts, width = at + (ends - width)[:n], width[:n]
    return words[starts >> 3] >> (starts & 7) & (1 << width) - 1


_ENDS = {m: np.cumsum(w) for m, w in _WIDTHS.items()}
_FULL = np.full(4096, 12)
_FULL_ENDS = np.cumsum(_FULL)


def _expanded(codes: np.ndarray, clear: int, limit: int) -> tuple[np.ndarray, int]:
    """The first ``limit`` samples of the codes between two clear codes, and how many samples these codes hold.

    The j-th code and the first sample of the next one make entry ``clear + 2 + j``, so an entry refers to an earlier
    code of the same run.  Chains of such references give sizes and first samples of all codes by doubled steps.
    """
    before, place = codes - (clear + 2), np.arange(len(codes))
    if (before >= place).any():
        raise ValueError("code beyond the table")
    single = before < 0
    first, steps = np.where(single, place, before), (~single).astype(np.int64)
    while True:
        after = first[first]
        if (after == first).all():
            break
        steps, first = steps + steps[first], after
    ends, tails, chained = np.cumsum(steps + 1), codes.copy(), np.flatnonzero(~single)
    size = int(ends[-1]) if len(ends) else 0
    tails[chained] = codes[first[before[chained] + 1]]
    shown = int(np.searchsorted(ends - steps - 1, limit))
    out = np.empty(int(ends[shown - 1]) if shown else 0, np.uint8)
    at, own = ends[:shown] - 1, place[:shown]
    while len(own):  # last samples of all codes, then the samples before these
        out[at] = tails[own]
        more = np.flatnonzero(~single[own])
        at, own = at[more] - 1, before[own[more]]
    return out[:limit], size


def lzw_decode(stream: bytes, min_bits: int, limit: int) -> bytes:
    """Samples of a code stream, at most ``limit`` of them."""
    if not 2 <= min_bits <= 8:
        raise ValueError("code size out of range")
    clear, end = 1 << min_bits, (1 << min_bits) + 1
    raw = np.zeros(len(stream) + 2, np.int64)
    raw[:-2] = np.frombuffer(stream, np.uint8)
    words = raw[:-2] | raw[1:-1] << 8 | raw[2:] << 16
    schedule, ends = _WIDTHS[min_bits], _ENDS[min_bits]
    out, at, size = [], 0, 0
    while at < 8 * len(stream) and size < limit:
        codes = _codes(words, at, ends, schedule)
        stop = np.flatnonzero((codes == clear) | (codes == end))
        while not len(stop):  # a full table: codes stay at 12 bits until a clear code
            done = len(codes)
            more = _codes(words, at + int(ends[-1]) + 12 * (done - len(schedule)), _FULL_ENDS, _FULL) if done >= len(schedule) else codes[:0]
            if not len(more):
                raise ValueError("the stream has no end code")
            codes = np.concatenate((codes, more))
            stop = np.flatnonzero((codes == clear) | (codes == end))
        k = int(stop[0])
        part, held = _expanded(codes[:k], clear, limit - size)
        out.append(part)
        size += held
        if codes[k] == end:
            break
        at += int(ends[min(k, len(ends) - 1)]) + 12 * max(0, k + 1 - len(ends))
    return b"".join(out)


def encode_payload(payload: bytes) -> bytes:
    """A GIF whose frames hold the payload; its length must be a positive multiple of ``WIDTH``."""
    rows = len(payload) // WIDTH
    if not rows or len(payload) % WIDTH:
        raise ValueError(f"length must be a positive multiple of {WIDTH}")
    out = [b"GIF89a", struct.pack("<HHBBB", WIDTH, min(rows, ROWS), 0xF7, 0, 0), _GREY]
    for top in range(0, rows, ROWS):
        part = payload[top * WIDTH : (top + ROWS) * WIDTH]
        out.append(struct.pack("<BBBBHBB", 0x21, 0xF9, 4, 2 << 2, DELAY, 0, 0))
        out.append(struct.pack("<BHHHHBB", 0x2C, 0, 0, WIDTH, len(part) // WIDTH, 0, 8))
        codes = lzw_encode(part)
        out += [bytes([len(codes[i : i + 255])]) + codes[i : i + 255] for i in range(0, len(codes), 255)]
        out.append(b"\0")
    out.append(b";")
    return b"".join(out)


@dataclass
class Frame:
    delay: int
    disposal: int
    indices: np.ndarray  # colour indices of the frame's own rectangle
    canvas: np.ndarray | None  # RGBA of the whole screen once the frame is drawn


def _sub_blocks(raw: bytes, at: int) -> tuple[bytes, int]:
    parts = []
    while raw[at]:
        parts.append(raw[at + 1 : at + 1 + raw[at]])
        at += 1 + raw[at]
    return b"".join(parts), at + 1


def decode(raw: bytes, compose: bool = True) -> list[Frame]:
    """Timed frames of a GIF."""
    return list(timed_frames(raw, compose))


def timed_frames(raw: bytes, compose: bool = True) -> Iterator[Frame]:
    """The frames one after another; no more than one canvas and a copy of it are held."""
    if raw[:6] not in (b"GIF87a", b"GIF89a"):
        raise ValueError("not a GIF")
    width, height, flags, _, _ = struct.unpack_from("<HHBBB", raw, 6)
    at = 13
    shared = None
    if flags & 128:
        n = 3 << (flags & 7) + 1
        shared, at = np.frombuffer(raw[at : at + n], np.uint8).reshape(-1, 3), at + n
    canvas = np.zeros((height, width, 4), np.uint8) if compose else None
    control = (0, 0, None)
    while True:
        if at >= len(raw):
            raise ValueError("the file has no trailer")
        kind = raw[at]
        if kind == 0x3B:
            return
        if kind == 0x21:
            data, end = _sub_blocks(raw, at + 2)
            if raw[at + 1] == 0xF9:
                packed, delay, clear = struct.unpack_from("<BHB", data)
                control = (packed >> 2 & 7, delay, clear if packed & 1 else None)
            at = end
        elif kind == 0x2C:
            left, top, w, h, flags = struct.unpack_from("<HHHHB", raw, at + 1)
            at += 10
            palette = shared
            if flags & 128:
                n = 3 << (flags & 7) + 1
                palette, at = np.frombuffer(raw[at : at + n], np.uint8).reshape(-1, 3), at + n
            stream, end = _sub_blocks(raw, at + 1)
            samples = np.frombuffer(lzw_decode(stream, raw[at], w * h), np.uint8)
            if len(samples) < w * h:
                raise ValueError("a frame is cut short")
            image, at = samples.reshape(h, w), end
            if flags & 64:
                order = [y for start, step in ((0, 8), (4, 8), (2, 4), (1, 2)) for y in range(start, h, step)]
                straight = np.empty_like(image)
                straight[order] = image
                image = straight
            disposal, delay, clear = control
            shown = None
            if compose:
                before = canvas.copy() if disposal == 3 else None
                area = canvas[top : top + h, left : left + w]
                part = image[: area.shape[0], : area.shape[1]]
                seen = ... if clear is None else part != clear
                drawn = part[seen]
                if drawn.size and (palette is None or drawn.max() >= len(palette)):
                    raise ValueError("a colour outside the palette")
                if drawn.size:
                    area[seen] = np.insert(palette, 3, 255, axis=1)[drawn]
                shown = canvas.copy()
                if disposal == 2:
                    canvas[top : top + h, left : left + w] = 0
                elif disposal == 3:
                    canvas = before
            yield Frame(delay, disposal, image, shown)
            control = (0, 0, None)
        else:
            raise ValueError(f"unknown block {kind:#x}")


def histogram(frames: Iterable[Frame]) -> list[int]:
    """Counts of drawn pixels of the composed canvases, by ``LEVELS`` of red, green and blue, over all frames."""
    total = np.zeros(LEVELS**3, np.int64)
    for f in frames:
        total += _colours(f.canvas)
    return total.tolist()


def _colours(canvas: np.ndarray) -> np.ndarray:
    red, green, blue, drawn = (canvas[:, :, i] // (256 // LEVELS) for i in range(4))
    colour = (red.astype(np.int16) * LEVELS + green) * LEVELS + blue
    return np.bincount(colour[drawn > 0], minlength=LEVELS**3)


def padded(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode("utf-8")
    rest = -len(raw) % WIDTH if raw else WIDTH
    return len(raw), raw + b" " * rest


def store_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Write ``(id, n_bytes, media)`` in the shared folder, the text's bytes as a GIF; returns the reread table."""

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                sizes, media, seen = [], [], {}
                for t in part.column(1).to_pylist():
                    n, payload = padded(t)
                    if payload not in seen:
                        seen[payload] = encode_payload(payload)
                    sizes.append(n)
                    media.append(seen[payload])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(media, pa.binary())], ["id", "n_bytes", "media"])

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return materialize(slim.mapInArrow(run, "id long, n_bytes long, media binary"), "media")


FEATURES = (
    "id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, "
    "timed array<struct<frame_no int, delay int, disposal int, colours array<int>, pixels array<long>>>"
)
_TIMED = pa.list_(
    pa.struct([("frame_no", pa.int32()), ("delay", pa.int32()), ("disposal", pa.int32()), ("colours", pa.list_(pa.int32())), ("pixels", pa.list_(pa.int64()))])
)


def describe(raw: bytes) -> tuple:
    """Payload and file sizes and digests of a GIF, and its timed frames."""
    digest, size, tail, timed = hashlib.sha256(), 0, b"", []
    for no, f in enumerate(timed_frames(raw)):
        part = f.indices.tobytes()
        digest.update(part)
        size, tail = size + len(part), (tail + part[-16:])[-16:]
        counts = _colours(f.canvas)
        met = np.flatnonzero(counts)
        timed.append({"frame_no": no, "delay": f.delay, "disposal": f.disposal, "colours": met, "pixels": counts[met]})
    return size, digest.hexdigest(), zlib.crc32(tail), len(raw), hashlib.sha256(raw).hexdigest(), timed


def media_features(media: DataFrame) -> DataFrame:
    """Decode and compose stored media; writes payload, file and timed frames of each row and returns the reread table."""
    arrow = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), _TIMED]
    names = ["id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "timed"]

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 256):
                ids, sizes, raws = (b.slice(at, 256).column(i).to_pylist() for i in range(3))
                seen = {r: None for r in raws}
                for r in seen:
                    seen[r] = describe(r)
                rows = [(i, n, *seen[r]) for i, n, r in zip(ids, sizes, raws)]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), arrow)], names)

    return materialize(media.select("id", "n_bytes", "media").mapInArrow(run, FEATURES), "media-frames")


def frame_table(features: DataFrame) -> DataFrame:
    """``(id, frame_no, delay, disposal, histogram)``, one row for each frame; the histogram gives pixels by colour."""
    frames = features.select("id", F.explode("timed").alias("f"))
    return frames.select("id", "f.frame_no", "f.delay", "f.disposal", F.map_from_arrays("f.colours", "f.pixels").alias("histogram"))


def totals(features: DataFrame) -> DataFrame:
    """``features`` with number of frames, summed delays and the histogram over all frames as ``colour:pixels`` in hexadecimal and decimal."""
    each = F.flatten(F.transform("timed", lambda f: F.arrays_zip(f["colours"].alias("colour"), f["pixels"].alias("n"))))
    added = lambda colour: F.aggregate(F.filter("each", lambda e: e["colour"] == colour), F.lit(0).cast("long"), lambda n, e: n + e["n"])
    shown = lambda colour: F.concat(F.lower(F.lpad(F.hex(colour), 3, "0")), F.lit(":"), added(colour).cast("string"))
    return features.withColumn("each", each).select(
        *features.columns,
        F.size("timed").alias("frames"),
        F.aggregate("timed", F.lit(0).cast("long"), lambda n, f: n + f["delay"]).alias("duration"),
        F.transform(F.array_sort(F.array_distinct(F.transform("each", lambda e: e["colour"]))), shown).alias("histogram"),
    )
