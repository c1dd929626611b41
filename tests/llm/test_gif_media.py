import hashlib
import struct
import zlib

import numpy as np
import pytest

from entlink.llm import gif_media as g


def plain_lzw(stream, min_bits):
    """Bit by bit, as the format defines it."""
    clear, end, pos, out = 1 << min_bits, (1 << min_bits) + 1, 0, b""
    width, table, last = min_bits + 1, [], None
    while True:
        code = sum((stream[(pos + i) // 8] >> ((pos + i) % 8) & 1) << i for i in range(width))
        pos += width
        if code == end:
            return out
        if code == clear:
            table, width, last = [bytes([i]) for i in range(clear)] + [b"", b""], min_bits + 1, None
            continue
        entry = table[code] if code < len(table) else last + last[:1]
        out += entry
        if last is not None and len(table) < 4096:
            table.append(last + entry[:1])
        if len(table) == 1 << width and width < 12:
            width += 1
        last = entry


@pytest.mark.parametrize("data", [b"", b"a", b"a" * 5000, bytes(range(256)) * 30, np.random.default_rng(0).bytes(20000), b"the cat sat " * 4000])
def test_lzw_round_trip(data):
    stream = g.lzw_encode(data)
    assert g.lzw_decode(stream, 8, len(data)) == data
    assert plain_lzw(stream, 8) == data


def test_small_code_sizes():
    rng = np.random.default_rng(1)
    for bits in (2, 4, 7):
        data = bytes(rng.integers(0, 1 << bits, 9000).tolist())
        stream = g.lzw_encode(data, bits)
        assert g.lzw_decode(stream, bits, len(data)) == data == plain_lzw(stream, bits)


def codes_stream(codes, min_bits):
    """A code stream as given, widths by the number of codes since the last clear code."""
    bits, k = "", 0
    for c in [1 << min_bits, *codes]:
        width = min_bits + 1
        while c != 1 << min_bits and k and width < 12 and (1 << min_bits) + 1 + k >= 1 << width:
            width += 1
        bits += format(c, f"0{width}b")[::-1]
        k = 0 if c == 1 << min_bits else k + 1
    return bytes(int(bits[i : i + 8][::-1], 2) for i in range(0, len(bits), 8))


def test_cut_streams_and_full_tables():
    rng = np.random.default_rng(2)
    for data in (b"ab" * 9000, rng.integers(97, 101, 30000).astype(np.uint8).tobytes()):
        stream = g.lzw_encode(data)
        for n in (1, 2, 3, 255, 5000, 17999):
            assert g.lzw_decode(stream, 8, n) == data[:n]
    # Entries that refer to the code just read, and a table that stays full.
    codes = [1, *range(6, 200), *rng.integers(0, 4, 4200).tolist(), *rng.integers(6, 4096, 300).tolist(), 5]
    stream = codes_stream(codes, 2)
    whole = plain_lzw(stream, 2)
    assert g.lzw_decode(stream, 2, len(whole)) == whole
    assert g.lzw_decode(stream, 2, 12345) == whole[:12345]


def test_codes_beyond_the_table_are_named():
    for codes in ([11, 9], [1, 11, 9], [1, 10, 12, 9]):
        with pytest.raises(ValueError):
            g.lzw_decode(codes_stream(codes, 3), 3, 100)


def test_payload_round_trip():
    for text in (None, "", "x", "é" * 96, "long " * 60000, "a\0b"):
        n, payload = g.padded(text)
        assert n == len((text or "").encode()) and len(payload) % 192 == 0 and payload
        frames = g.decode(g.encode_payload(payload))
        assert b"".join(f.indices.tobytes() for f in frames) == payload
        assert (frames[0].canvas[: frames[0].indices.shape[0], :, 0] == frames[0].indices).all()
        assert sum(g.histogram(frames)) == len(payload)


def frame(left, top, rows, disposal, clear, delay=5, interlace=False):
    h, w = len(rows), len(rows[0])
    order = [y for s, k in ((0, 8), (4, 8), (2, 4), (1, 2)) for y in range(s, h, k)] if interlace else range(h)
    codes = g.lzw_encode(b"".join(bytes(rows[y]) for y in order), 2)
    head = struct.pack("<BBBBHBB", 0x21, 0xF9, 4, disposal << 2 | (clear is not None), delay, clear or 0, 0)
    return head + struct.pack("<BHHHHBB", 0x2C, left, top, w, h, 64 * interlace, 2) + bytes([len(codes)]) + codes + b"\0"


def test_disposal_transparency_interlace():
    palette = bytes([0, 0, 0, 255, 0, 0, 0, 255, 0, 0, 0, 255])
    raw = b"GIF89a" + struct.pack("<HHBBB", 2, 2, 0x81, 0, 0) + palette
    raw += frame(0, 0, [[1, 1], [1, 1]], 1, None) + frame(0, 0, [[2, 0], [0, 2]], 3, 0, 7) + frame(1, 1, [[3]], 2, None) + frame(0, 0, [[0, 2], [0, 0]], 0, 0, interlace=True) + b";"
    f = g.decode(raw)
    assert [x.delay for x in f] == [5, 7, 5, 5]
    red, green, blue, none = [255, 0, 0, 255], [0, 255, 0, 255], [0, 0, 255, 255], [0, 0, 0, 0]
    assert f[1].canvas.tolist() == [[green, red], [red, green]]
    assert f[2].canvas.tolist() == [[red, red], [red, blue]]
    assert f[3].canvas.tolist() == [[red, green], [red, none]]
    with pytest.raises(ValueError):
        g.decode(raw[:-1])


def test_media_table(spark):
    texts = [None, "", "x", "x", "é à", "long text " * 9000]
    docs = spark.createDataFrame([(i, t, "m") for i, t in enumerate(texts)] + [(None, "x", "m")], "doc_id long, text string, media string")
    rows = g.media_features(g.store_media(docs)).collect()
    assert len(rows) == 7
    for r in rows:
        if r.id is None:
            continue
        n, payload = g.padded(texts[r.id])
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (n, len(payload), hashlib.sha256(payload).hexdigest())
        assert r.tail_crc32 == zlib.crc32(payload[-16:])
    assert g.media_features(g.store_media(docs.where("false"))).count() == 0


def test_features_compose_palette_disposal_and_transparency(spark):
    palette = bytes([0, 0, 0, 255, 0, 0, 0, 255, 0, 0, 0, 255])
    raw = b"GIF89a" + struct.pack("<HHBBB", 2, 2, 0x81, 0, 0) + palette
    raw += frame(0, 0, [[1, 1], [1, 1]], 1, None) + frame(0, 0, [[2, 0], [0, 2]], 3, 0, 7) + frame(1, 1, [[3]], 2, None) + frame(0, 0, [[0, 2], [0, 0]], 0, 0) + b";"
    found = g.media_features(spark.createDataFrame([(1, 9, raw), (None, 9, raw)], "id long, n_bytes long, media binary"))
    rows = sorted((r for r in g.frame_table(found).collect() if r.id == 1), key=lambda r: r.frame_no)
    assert [(r.delay, r.disposal) for r in rows] == [(5, 1), (7, 3), (5, 2), (5, 0)]
    red, green, blue = 0xF00, 0x0F0, 0x00F
    assert [r.histogram for r in rows] == [{red: 4}, {red: 2, green: 2}, {red: 3, blue: 1}, {red: 2, green: 1}]
    for r in g.totals(found).collect():
        assert (r.frames, r.duration, r.histogram) == (4, 22, ["00f:1", "0f0:3", "f00:11"])
    with pytest.raises(ValueError):
        g.decode(raw[:10] + b"\0\0\0" + raw[25:])
