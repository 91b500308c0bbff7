"""Sorted-string-table shards of token ids: an immutable file per key range.

File layout (all integers little-endian)::

    magic "TOKSST01"
    data block *      zstd frame of entries and restart offsets, then crc32 of the frame
    index block       per data block: last key, offset, stored size, raw size
    bloom block       bit array
    footer (72 bytes) offsets and sizes of both blocks, counts, hash count, crc32, magic

An entry is ``varint shared, varint rest, varint value size, key rest, value``: the key keeps
only what differs from the key before it, except at every 16th entry (a restart), from which a
reader can search. Keys are 9 bytes and sort as the identifiers do: one byte 0 for a null
identifier (then eight zero bytes), else 1, and the big-endian integer with its sign bit
flipped. A value is one byte of id width (2 or 4) and the ids.

Repeated identifiers are kept as repeated keys, in the order written; ``get_all`` returns all.
"""

from __future__ import annotations

import struct
import zlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import zstandard

MAGIC = b"TOKSST01"
FOOTER = struct.Struct("<QQQQQQQIII4x")
RESTART = 16


def encode_key(x: int | None) -> bytes:
    return b"\x00" * 9 if x is None else b"\x01" + ((x + (1 << 63)) & ((1 << 64) - 1)).to_bytes(8, "big")


def decode_key(b: bytes) -> int | None:
    return None if b[0] == 0 else int.from_bytes(b[1:], "big") - (1 << 63)


def _varint(n: int) -> bytes:
    if n < 128:
        return bytes((n,))
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(b: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        x = b[at]
        at += 1
        n |= (x & 127) << shift
        if x < 128:
            return n, at
        shift += 7


def _probes(key: bytes, n_hash: int, n_bits: int) -> list[int]:
    """Double hashing: two independent 32-bit checksums give all probes."""
    a, b = zlib.crc32(key), zlib.adler32(key[::-1]) * 2654435761 & 0xFFFFFFFF | 1
    return [(a + i * b) % n_bits for i in range(n_hash)]


class Writer:
    """Appends entries in ascending key order to a binary sink; holds one data block."""

    def __init__(self, sink, block_bytes: int = 1 << 16, bits_per_key: int = 10):
        self.sink, self.block_bytes, self.bits_per_key = sink, block_bytes, bits_per_key
        self.pack = zstandard.ZstdCompressor(level=1)
        self.at = self.n = 0
        self.index: list[tuple[bytes, int, int, int]] = []
        self.keys: list[bytes] = []  # 9 bytes each, for the filter
        self.last = b""
        self._put(MAGIC)
        self._open_block()

    def _put(self, b: bytes) -> None:
        self.sink.write(b)
        self.at += len(b)

    def _open_block(self) -> None:
        self.parts: list[bytes] = []
        self.size = self.in_block = 0
        self.restarts: list[int] = []

    def add(self, key: bytes, ids: np.ndarray) -> None:
        if key < self.last:
            raise ValueError("keys must come in ascending order")
        shared = 0
        if self.in_block % RESTART == 0:
            self.restarts.append(self.size)
        else:
            while shared < 9 and key[shared] == self.last[shared]:
                shared += 1
        wide = len(ids) and int(ids.max()) > 0xFFFF
        value = b"\x04" + ids.astype("<u4").tobytes() if wide else b"\x02" + ids.astype("<u2").tobytes()
        head = _varint(shared) + _varint(9 - shared) + _varint(len(value)) + key[shared:]
        self.parts += [head, value]
        self.size += len(head) + len(value)
        if key != self.last or not self.n:
            self.keys.append(key)
        self.last = key
        self.in_block += 1
        self.n += 1
        if self.size >= self.block_bytes:
            self._close_block()

    def _close_block(self) -> None:
        if not self.in_block:
            return
        raw = b"".join(self.parts) + np.asarray(self.restarts, "<u4").tobytes() + struct.pack("<I", len(self.restarts)) if self.size < 1 << 32 else None
        if raw is None:  # one huge value: a single restart at 0
            raw = b"".join(self.parts) + struct.pack("<II", 0, 1)
        frame = self.pack.compress(raw)
        self.index.append((self.last, self.at, len(frame), len(raw)))
        self._put(frame)
        self._put(struct.pack("<I", zlib.crc32(frame)))
        self._open_block()

    def finish(self) -> int:
        self._close_block()
        index_at = self.at
        self._put(b"".join(k + struct.pack("<QQQ", *rest) for k, *rest in self.index))
        bloom_at = self.at
        n_bits = max(64, len(self.keys) * self.bits_per_key)
        n_hash = max(1, round(self.bits_per_key * 0.69))
        bits = np.zeros((n_bits + 7) // 8, np.uint8)
        for key in self.keys:
            for p in _probes(key, n_hash, n_bits):
                bits[p >> 3] |= 1 << (p & 7)
        self._put(bits.tobytes())
        fields = (index_at, bloom_at - index_at, bloom_at, len(bits), n_bits, self.n, len(self.index))
        crc = zlib.crc32(struct.pack("<7Q", *fields))
        self._put(FOOTER.pack(*fields, n_hash, crc, 0) + MAGIC)
        return self.at


class Reader:
    """Point lookups and an ordered scan over one shard; reads a block at a time."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        tail = FOOTER.size + len(MAGIC)
        foot = self._at(size - tail, tail)
        if foot[-len(MAGIC) :] != MAGIC or self._at(0, len(MAGIC)) != MAGIC:
            raise ValueError("not a shard of this format")
        *fields, self.n_hash, crc, _ = FOOTER.unpack(foot[: FOOTER.size])
        if crc != zlib.crc32(struct.pack("<7Q", *fields)):
            raise ValueError("the footer is damaged")
        index_at, index_size, bloom_at, bloom_size, self.n_bits, self.n, _ = fields
        raw = self._at(index_at, index_size)
        self.blocks = [(raw[i : i + 9], *struct.unpack_from("<QQQ", raw, i + 9)) for i in range(0, index_size, 33)]
        self.last_keys = [b[0] for b in self.blocks]
        self.bloom = self._at(bloom_at, bloom_size)
        self.unpack = zstandard.ZstdDecompressor()

    def _at(self, at: int, n: int) -> bytes:
        self.source.seek(at)
        return self.source.read(n)

    def _block(self, i: int) -> tuple[bytes, list[int]]:
        _, at, stored, size = self.blocks[i]
        frame = self._at(at, stored + 4)
        if struct.unpack("<I", frame[stored:])[0] != zlib.crc32(frame[:stored]):
            raise ValueError(f"block {i} is damaged")
        raw = self.unpack.decompress(frame[:stored], max_output_size=size)
        n = struct.unpack_from("<I", raw, len(raw) - 4)[0]
        restarts = np.frombuffer(raw, "<u4", n, len(raw) - 4 - 4 * n).tolist()
        return raw[: len(raw) - 4 - 4 * n], restarts

    @staticmethod
    def _entries(raw: bytes, at: int, key: bytes = b"") -> Iterator[tuple[bytes, np.ndarray]]:
        while at < len(raw):
            shared, at = _read_varint(raw, at)
            rest, at = _read_varint(raw, at)
            size, at = _read_varint(raw, at)
            key = key[:shared] + raw[at : at + rest]
            at += rest
            width = raw[at]
            yield key, np.frombuffer(raw, "<u2" if width == 2 else "<u4", (size - 1) // width, at + 1)
            at += size

    def scan(self) -> Iterator[tuple[int | None, np.ndarray]]:
        for i in range(len(self.blocks)):
            for key, ids in self._entries(self._block(i)[0], 0):
                yield decode_key(key), ids

    def get_all(self, x: int | None) -> list[np.ndarray]:
        """All values of a key: filter, then index, then restarts, then entries."""
        key = encode_key(x)
        if not all(self.bloom[p >> 3] >> (p & 7) & 1 for p in _probes(key, self.n_hash, self.n_bits)):
            return []
        found, i = [], bisect_left(self.last_keys, key)
        while i < len(self.blocks):
            raw, restarts = self._block(i)
            lo, hi = 0, len(restarts) - 1
            while lo < hi:  # the last restart whose key is below the one sought
                mid = (lo + hi + 1) // 2
                if next(self._entries(raw, restarts[mid]))[0] < key:
                    lo = mid
                else:
                    hi = mid - 1
            for k, ids in self._entries(raw, restarts[lo]):
                if k == key:
                    found.append(ids)
                elif k > key:
                    return found
            i += 1
        return found

    def get(self, x: int | None) -> np.ndarray | None:
        found = self.get_all(x)
        return found[0] if found else None
