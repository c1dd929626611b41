"""Sorted-string-table files: ordered keys, byte values, lookup by binary search.

Layout: data blocks, index block, Bloom filter, footer.  A data block holds
entries ``shared, unshared, value length`` (varints), the unshared key bytes
and the value; keys share their prefix with the entry before.  Blocks are
compressed with zstd and carry a crc32.  The index has the last key, offset
and length of each block.  The footer is of fixed size and ends in a magic.
"""

from __future__ import annotations

import bisect
import json
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import xxhash
import zstandard

MAGIC = b"ENTLSST1"
FOOTER = struct.Struct("<QQQQQ8s")
BLOCK_BYTES = 1 << 16
BLOOM_BITS, BLOOM_HASHES = 10, 7


def _varint(n: int, out: bytearray) -> None:
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)


def _read_varint(buf: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = buf[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def _bloom_positions(keys: list[bytes], bits: int) -> np.ndarray:
    h = np.array([xxhash.xxh64_intdigest(k) for k in keys], np.uint64)
    low, high = h & np.uint64(0xFFFFFFFF), h >> np.uint64(32) | np.uint64(1)
    return (low[:, None] + high[:, None] * np.arange(BLOOM_HASHES, dtype=np.uint64)) % np.uint64(bits)


class Writer:
    """Appends entries in key order; equal keys are allowed and keep their order."""

    def __init__(self, out, meta: dict | None = None):
        self.out, self.meta, self.at = out, meta or {}, 0
        self.block, self.last, self.keys, self.index = bytearray(), b"", [], []
        self.squeeze = zstandard.ZstdCompressor(level=1)

    def add(self, key: bytes, value: bytes) -> None:
        if self.keys and key < self.keys[-1]:
            raise ValueError("keys must not fall")
        shared = 0
        while shared < len(key) and shared < len(self.last) and key[shared] == self.last[shared]:
            shared += 1
        for n in (shared, len(key) - shared, len(value)):
            _varint(n, self.block)
        self.block += key[shared:]
        self.block += value
        self.last = key
        self.keys.append(key)
        if len(self.block) >= BLOCK_BYTES:
            self._flush()

    def _put(self, data: bytes) -> None:
        self.out.write(data)
        self.at += len(data)

    def _flush(self) -> None:
        if self.block:
            packed = self.squeeze.compress(bytes(self.block))
            self.index.append([self.last.hex(), self.at, len(packed)])
            self._put(packed + struct.pack("<I", zlib.crc32(packed)))
            self.block, self.last = bytearray(), b""

    def close(self) -> None:
        self._flush()
        index_at = self.at
        self._put(zstandard.compress(json.dumps({"blocks": self.index, "meta": self.meta}).encode()))
        bloom_at = self.at
        bits = max(64, -(-len(self.keys) * BLOOM_BITS // 8) * 8)
        field = np.zeros(bits, np.uint8)
        if self.keys:
            field[_bloom_positions(self.keys, bits).ravel().astype(np.int64)] = 1
        self._put(np.packbits(field).tobytes())
        self._put(FOOTER.pack(index_at, bloom_at, self.at, bits, len(self.keys), MAGIC))


class Reader:
    """Reads a table from any file with ``seek`` and ``read``."""

    def __init__(self, file):
        self.file = file
        file.seek(0, 2)
        end = file.tell()
        if end < FOOTER.size:
            raise ValueError("too short for a table")
        self.index_at, self.bloom_at, bloom_end, self.bits, self.count, magic = FOOTER.unpack(self._at(end - FOOTER.size, FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a table of this format")
        head = json.loads(zstandard.decompress(self._at(self.index_at, self.bloom_at - self.index_at)))
        self.blocks = [(bytes.fromhex(k), at, n) for k, at, n in head["blocks"]]
        self.meta = head["meta"]
        self.bloom_bytes = bloom_end - self.bloom_at
        self.bloom = None

    def _at(self, at: int, n: int) -> bytes:
        self.file.seek(at)
        return self.file.read(n)

    def _entries(self, block: int) -> Iterator[tuple[bytes, bytes]]:
        _, at, n = self.blocks[block]
        raw = self._at(at, n + 4)
        if zlib.crc32(raw[:n]) != struct.unpack("<I", raw[n:])[0]:
            raise ValueError(f"block {block} is damaged")
        buf, key, p = zstandard.decompress(raw[:n]), b"", 0
        while p < len(buf):
            shared, p = _read_varint(buf, p)
            own, p = _read_varint(buf, p)
            size, p = _read_varint(buf, p)
            key = key[:shared] + buf[p : p + own]
            yield key, buf[p + own : p + own + size]
            p += own + size

    def __iter__(self) -> Iterator[tuple[bytes, bytes]]:
        for b in range(len(self.blocks)):
            yield from self._entries(b)

    def may_hold(self, key: bytes) -> bool:
        if self.bloom is None:
            self.bloom = np.unpackbits(np.frombuffer(self._at(self.bloom_at, self.bloom_bytes), np.uint8))
        return bool(self.bloom[_bloom_positions([key], self.bits).astype(np.int64)].all())

    def get(self, key: bytes) -> list[bytes]:
        """All values of a key: Bloom filter, then binary search of the index, then one or more blocks."""
        if not self.may_hold(key):
            return []
        found = []
        for b in range(bisect.bisect_left([k for k, _, _ in self.blocks], key), len(self.blocks)):
            for k, v in self._entries(b):
                if k == key:
                    found.append(v)
                elif k > key:
                    return found
        return found
