"""Bitmaps in numpy and the codecs that keep them: word-aligned, byte-aligned and word-run, and raw.

All codecs see a bitmap as runs of equal units (31 bits, 8 bits, 64 bits). They differ in which runs they may shorten
and in how they write them. Boolean operations walk the runs of both sides without going back to bits.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass

import numpy as np


def pack(bits: np.ndarray) -> bytes:
    """Bits (bool) -> little-endian 64-bit words."""
    raw = np.packbits(bits, bitorder="little").tobytes()
    return raw + b"\0" * (-len(raw) % 8)


def unpack(raw: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(raw, np.uint8), count=n, bitorder="little").astype(bool)


@dataclass
class Runs:
    """Units with repeat counts, over n bits."""

    n: int
    units: np.ndarray
    counts: np.ndarray


class Codec:
    unit_bits = 64
    name = "raw"

    # ---- bits <-> runs

    def units(self, bits: np.ndarray) -> np.ndarray:
        k = -(-len(bits) // self.unit_bits)
        padded = np.zeros(k * self.unit_bits, np.uint8)
        padded[: len(bits)] = bits
        rows = padded.reshape(k, self.unit_bits)
        out = np.zeros((k, 8), np.uint8)
        packed = np.packbits(rows, axis=1, bitorder="little")
        out[:, : packed.shape[1]] = packed
        return out.view("<u8").ravel()

    def may_repeat(self, units: np.ndarray) -> np.ndarray:
        """Which units a run may hold more than once."""
        full = np.uint64((1 << self.unit_bits) - 1)
        return (units == 0) | (units == full)

    def runs(self, n: int, units: np.ndarray, counts: np.ndarray | None = None) -> Runs:
        counts = np.ones(len(units), np.int64) if counts is None else counts
        if len(units) < 2:
            return Runs(n, units, counts)
        new = np.concatenate([[True], (units[1:] != units[:-1]) | ~self.may_repeat(units[1:])])
        at = np.flatnonzero(new)
        return Runs(n, units[at], np.add.reduceat(counts, at))

    def bits(self, r: Runs) -> np.ndarray:
        units = np.repeat(r.units, r.counts)
        return np.unpackbits(units.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")[:, : self.unit_bits].ravel()[: r.n].astype(bool)

    # ---- bytes

    def encode(self, bits: np.ndarray) -> bytes:
        return self.write(self.runs(len(bits), self.units(np.asarray(bits, bool))))

    def encode_many(self, bitmaps: list[np.ndarray]) -> list[bytes]:
        """encode() of each."""
        return [self.encode(b) for b in bitmaps]

    def encode_ones(self, n: int, rows: int, row: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, bytes]:
        """encode() of so many bitmaps of n bits from their ones, each given once: where each ends, and all bytes."""
        at, out = np.argsort(row, kind="stable"), []
        for own in np.split(place[at], np.searchsorted(row[at], np.arange(1, rows))):
            bits = np.zeros(n, bool)
            bits[own] = True
            out.append(self.encode(bits))
        return np.cumsum([len(b) for b in out[:rows]], dtype=np.int64), b"".join(out[:rows])

    def decode(self, raw: bytes) -> np.ndarray:
        return self.bits(self.read(raw))

    def write(self, r: Runs) -> bytes:
        return struct.pack("<Q", r.n) + np.repeat(r.units, r.counts).astype("<u8").tobytes()

    def read(self, raw: bytes) -> Runs:
        (n,) = struct.unpack_from("<Q", raw)
        return self.runs(n, np.frombuffer(raw, "<u8", offset=8))

    # ---- operations on the encoded form

    def combine(self, a: bytes, b: bytes, op) -> bytes:
        x, y = self.read(a), self.read(b)
        if x.n != y.n:
            raise ValueError("bitmaps of unequal length")
        ex, ey = np.cumsum(x.counts), np.cumsum(y.counts)
        ends = np.union1d(ex, ey)
        units = op(x.units[np.searchsorted(ex, ends)], y.units[np.searchsorted(ey, ends)]) if len(ends) else x.units
        return self.write(self.runs(x.n, units, np.diff(ends, prepend=0)))

    def and_(self, a: bytes, b: bytes) -> bytes:
        return self.combine(a, b, np.bitwise_and)

    def or_(self, a: bytes, b: bytes) -> bytes:
        return self.combine(a, b, np.bitwise_or)

    def xor(self, a: bytes, b: bytes) -> bytes:
        return self.combine(a, b, np.bitwise_xor)

    def andnot(self, a: bytes, b: bytes) -> bytes:
        return self.combine(a, b, lambda x, y: x & ~y)

    def not_(self, a: bytes) -> bytes:
        """Bits past the end stay zero."""
        r = self.read(a)
        ones = self.encode(np.ones(r.n, bool))
        return self.xor(a, ones)

    def count(self, a: bytes) -> int:
        r = self.read(a)
        return int((np.bitwise_count(r.units) * r.counts).sum())

    def positions(self, a: bytes) -> np.ndarray:
        return np.flatnonzero(self.decode(a))


class WordAligned(Codec):
    """32-bit words: a literal holds 31 bits; a fill has the top bit, its value in the next, and the number of groups."""

    unit_bits = 31
    name = "wah"
    MOST = (1 << 30) - 1

    def write(self, r: Runs) -> bytes:
        return struct.pack("<Q", r.n) + self._words(r)[0].tobytes()

    def encode_many(self, bitmaps: list[np.ndarray]) -> list[bytes]:
        """All at once where lengths are equal: bitmaps follow one another, and no run goes on into the next."""
        n = len(bitmaps[0]) if bitmaps else 0
        if not n or any(len(b) != n for b in bitmaps):
            return super().encode_many(bitmaps)
        k = -(-n // self.unit_bits)
        rows = np.zeros((len(bitmaps), k * self.unit_bits), np.uint8)
        rows[:, :n] = np.stack(bitmaps)
        units = self.units(rows.ravel())
        new = np.ones(len(units), bool)
        new[1:] = (units[1:] != units[:-1]) | ~self.may_repeat(units[1:])
        new[::k] = True
        at = np.flatnonzero(new)
        words, pieces = self._words(Runs(n, units[at], np.diff(at, append=len(units))))
        ends = np.cumsum(pieces)[np.searchsorted(at, np.arange(1, len(bitmaps) + 1) * k) - 1]
        head = struct.pack("<Q", n)
        return [head + words[a:b].tobytes() for a, b in zip([0, *ends[:-1]], ends)]

    def encode_ones(self, n: int, rows: int, row: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, bytes]:
        """Only groups that hold a one are looked at, those of all bitmaps together."""
        k, full = -(-n // self.unit_bits), (1 << self.unit_bits) - 1
        if k > self.MOST or not rows:
            return super().encode_ones(n, rows, row, place)
        ones = np.sort((row.astype(np.int64) * k + place // self.unit_bits) << 5 | place % self.unit_bits)
        unit = ones >> 5
        first = np.flatnonzero(np.concatenate([[True], unit[1:] != unit[:-1]])[: len(unit)])
        word = np.add.reduceat(np.int64(1) << (ones & 31), first) if len(first) else ones
        unit = unit[first]
        of = unit // k
        # full groups that follow one another within a bitmap are one run
        new = np.ones(len(unit), bool)
        new[1:] = (unit[1:] != unit[:-1] + 1) | (of[1:] != of[:-1]) | (word[1:] != full) | (word[:-1] != full)
        run = np.flatnonzero(new)
        count = np.diff(run, append=len(unit))
        word, of, begin = np.where(count > 1, 3 << 30 | count, word[run]), of[run], unit[run]
        end = begin + count
        gap = begin - np.where(np.concatenate([[True], of[1:] != of[:-1]])[: len(of)], of * k, np.concatenate([[0], end])[: len(of)])
        rest = np.full(rows, k)
        last = np.flatnonzero(np.concatenate([of[1:] != of[:-1], [True]])[: len(of)])
        rest[of[last]] = (of[last] + 1) * k - end[last]
        # each bitmap: its length in two words, then empty groups and run in turn, then the empty groups at its end
        size = 1 + (gap > 0)
        own = np.bincount(of, size, rows).astype(np.int64)
        ends = np.cumsum(2 + own + (rest > 0))
        out = np.zeros(int(ends[-1]), "<u4")
        start = ends - (2 + own + (rest > 0))
        out[start], out[start + 1] = n & 0xFFFFFFFF, n >> 32
        at = start[of] + 1 + np.cumsum(size) - (np.cumsum(own) - own)[of]
        empty = lambda groups: np.where(groups > 1, 2 << 30 | groups, 0)
        out[at] = word
        out[at[gap > 0] - 1] = empty(gap[gap > 0])
        out[ends[rest > 0] - 1] = empty(rest[rest > 0])
        return ends * 4, out.tobytes()

    def _words(self, r: Runs) -> tuple[np.ndarray, np.ndarray]:
        """The words, and how many each run takes."""
        fill = self.may_repeat(r.units) & (r.counts > 1)
        value = (r.units > 0).astype(np.uint64)
        pieces = np.where(fill, -(-r.counts // self.MOST), 1)
        word = np.where(fill, np.uint64(1 << 31) | (value << np.uint64(30)), r.units)
        words = np.repeat(word, pieces)
        isfill, left = np.repeat(fill, pieces), np.repeat(r.counts, pieces)
        nth = np.arange(len(words)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        amount = np.minimum(left - nth * self.MOST, self.MOST).astype(np.uint64)
        words = np.where(isfill, words | amount, words)
        return words.astype("<u4"), pieces

    def read(self, raw: bytes) -> Runs:
        (n,) = struct.unpack_from("<Q", raw)
        w = np.frombuffer(raw, "<u4", offset=8).astype(np.uint64)
        fill = (w >> np.uint64(31)) == 1
        units = np.where(fill, np.where((w >> np.uint64(30)) & np.uint64(1) == 1, np.uint64((1 << 31) - 1), np.uint64(0)), w)
        return self.runs(n, units, np.where(fill, w & np.uint64(self.MOST), np.uint64(1)).astype(np.int64))


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(raw: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = raw[at]
        n |= (b & 127) << shift
        at, shift = at + 1, shift + 7
        if b < 128:
            return n, at


class ByteAligned(Codec):
    """Runs of 0x00 or 0xFF bytes, each followed by literal bytes: header (fill value, run length), literal count, literals."""

    unit_bits = 8
    name = "bbc"

    def write(self, r: Runs) -> bytes:
        out = [struct.pack("<Q", r.n)]
        i, units, counts = 0, r.units.tolist(), r.counts.tolist()
        while i < len(units):
            fill, length = 0, 0
            if units[i] in (0, 255):
                fill, length = int(units[i] == 255), counts[i]
                i += 1
            j = i
            while j < len(units) and units[j] not in (0, 255):
                j += 1
            out += [_varint(length << 1 | fill), _varint(j - i), bytes(units[i:j])]
            i = j
        return b"".join(out)

    def read(self, raw: bytes) -> Runs:
        (n,) = struct.unpack_from("<Q", raw)
        at, units, counts = 8, [], []
        while at < len(raw):
            head, at = _read_varint(raw, at)
            k, at = _read_varint(raw, at)
            if head >> 1:
                units.append(255 if head & 1 else 0)
                counts.append(head >> 1)
            units += raw[at : at + k]
            counts += [1] * k
            at += k
        return self.runs(n, np.array(units, np.uint64), np.array(counts, np.int64))


class WordRun(Codec):
    """Runs of any repeated 64-bit word, which pays off when rows are stretched to words."""

    unit_bits = 64
    name = "wordrun"

    def may_repeat(self, units: np.ndarray) -> np.ndarray:
        return np.ones(len(units), bool)

    def write(self, r: Runs) -> bytes:
        return struct.pack("<Q", r.n) + b"".join(_varint(c) + struct.pack("<Q", u) for u, c in zip(r.units.tolist(), r.counts.tolist()))

    def read(self, raw: bytes) -> Runs:
        (n,) = struct.unpack_from("<Q", raw)
        at, units, counts = 8, [], []
        while at < len(raw):
            c, at = _read_varint(raw, at)
            units.append(struct.unpack_from("<Q", raw, at)[0])
            counts.append(c)
            at += 8
        return self.runs(n, np.array(units, np.uint64), np.array(counts, np.int64))


CODECS: dict[str, Codec] = {c.name: c for c in (Codec(), WordAligned(), ByteAligned(), WordRun())}
