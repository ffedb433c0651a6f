"""Encodings of a binned bitmap index, and how few bitmaps a range of bins needs.

Bins are numbered 0..B-1 here. stored() gives the bitmaps of an encoding, bin_range() the cells of bins i..j from
them, with the number of bitmaps read. `present` is the bitmap of non-empty cells, kept by every index.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

#: One bitmap a bin; bins 0..i; half of the bins from k on; and the composites: a bitmap for each bit of the bin's
#: number; for each digit of it in mixed radix, range encoded; and one for each bin and for each group of bins.
ENCODINGS = ("equality", "range", "interval", "bit_sliced", "components", "two_level")
#: Lower radix of "components", and bins in a group of "two_level".
GROUP = 8


def bases_of(bins: int) -> tuple[int, ...]:
    """Radices of a bin's number, the lowest first."""
    return (bins,) if bins <= GROUP else (GROUP, -(-bins // GROUP))


def stored(bin_of: np.ndarray, bins: int, encoding: str) -> list[np.ndarray]:
    """bin_of: bin of each cell, -1 for empty cells. Equality: one bitmap a bin. Range: cells of bins 0..i, for i < B - 1.
    Interval: with B made even and m = B / 2, cells of bins k..k + m - 1, for k < m."""
    present = bin_of >= 0
    if encoding == "equality":
        return [bin_of == b for b in range(bins)]
    if encoding == "range":
        return [present & (bin_of <= i) for i in range(bins - 1)]
    if encoding == "interval":
        m = (bins + 1) // 2
        return [(bin_of >= k) & (bin_of < k + m) for k in range(m)]
    if encoding == "bit_sliced":
        return [((bin_of >> s) & 1).astype(bool) & present for s in range(bitmap_count(bins, encoding))]
    if encoding == "components":
        bases = bases_of(bins)
        return [present & (d <= i) for d, b in zip(digits(bin_of, bases), bases) for i in range(b - 1)]
    if encoding == "two_level":
        return [bin_of == b for b in range(bins)] + [present & (bin_of // GROUP == g) for g in range(-(-bins // GROUP))]
    raise ValueError(encoding)


#: Encodings of which a bin's cells are in bitmaps that follow one another.
IN_A_ROW = ("equality", "range", "interval")


def held_by(bin_of: np.ndarray, bins: int | np.ndarray, encoding: str) -> tuple[np.ndarray, np.ndarray]:
    """For the bin of each cell the bitmaps of stored() that hold it: from the first up to the second, which does not."""
    if encoding == "equality":
        return bin_of, bin_of + 1
    if encoding == "range":
        return bin_of, np.maximum(bin_of, bins - 1)
    if encoding == "interval":
        m = (bins + 1) // 2
        return np.maximum(0, bin_of - m + 1), np.minimum(bin_of + 1, m)
    raise ValueError(encoding)


def spread(first: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All numbers from each first up to its end, and whose they are."""
    n = end - first
    owner = np.repeat(np.arange(len(n)), n)
    return np.arange(len(owner)) - (np.cumsum(n) - n - first)[owner], owner


def bitmap_count(bins: int, encoding: str) -> int:
    composite = {"bit_sliced": max(1, (bins - 1).bit_length()), "components": sum(b - 1 for b in bases_of(bins)), "two_level": bins + -(-bins // GROUP)}
    return ({"equality": bins, "range": bins - 1, "interval": (bins + 1) // 2} | composite)[encoding]


def bin_range(read: Callable[[int], np.ndarray], present: np.ndarray, bins: int, encoding: str, i: int, j: int) -> tuple[np.ndarray, int]:
    """(cells of bins i..j, bitmaps read); read(k) fetches the k-th stored bitmap."""
    if i > j:
        return np.zeros_like(present), 0
    if i == 0 and j == bins - 1:
        return present, 0
    if encoding in ("bit_sliced", "components"):
        opened: dict[int, np.ndarray] = {}

        def once(k: int) -> np.ndarray:
            if k not in opened:
                opened[k] = read(k)
            return opened[k]

        if encoding == "bit_sliced":
            n = bitmap_count(bins, encoding)
            under = lambda bound: sliced_below([once(k) for k in range(n)], present, bound)
        else:
            bases, parts, at = bases_of(bins), [], 0
            for b in bases:
                parts.append([at + k for k in range(b - 1)])
                at += b - 1
            under = lambda bound: components_below(parts, present, bases, bound, once)
        upper = present if j == bins - 1 else under(j + 1)
        out = upper & ~under(i) if i else upper
        return out, len(opened)
    if encoding == "two_level":
        out, n = np.zeros_like(present), 0
        k = i
        while k <= j:
            if k % GROUP == 0 and min(k + GROUP, bins) - 1 <= j:  # a whole group
                out, n, k = out | read(bins + k // GROUP), n + 1, k + GROUP
            else:
                out, n, k = out | read(k), n + 1, k + 1
        return out, n
    if encoding == "equality":
        if j - i + 1 > bins // 2:
            others = [b for b in range(bins) if not i <= b <= j]
            return present & ~np.logical_or.reduce([read(b) for b in others]), len(others)
        return np.logical_or.reduce([read(b) for b in range(i, j + 1)]), j - i + 1
    if encoding == "range":
        upper, n = (present, 0) if j == bins - 1 else (read(j), 1)
        return (upper, n) if i == 0 else (upper & ~read(i - 1), n + 1)
    m = (bins + 1) // 2  # the interval starting at k holds bins k..k+m-1
    if j == bins - 1:
        below, n = bin_range(read, present, 2 * m, encoding, 0, i - 1)
        return present & ~below, n
    w = j - i + 1
    if w == m and i < m:
        return read(i), 1
    if w > m:
        return read(i) | read(j - m + 1), 2
    if i < m <= j + 1:
        return read(i) & read(j - m + 1), 2
    if j < m - 1:
        return read(i) & ~read(j + 1), 2
    return read(j - m + 1) & ~read(i - m), 2


def bit_slices(ranks: np.ndarray, present: np.ndarray) -> list[np.ndarray]:
    """Bit-sliced index: bitmap s holds bit s of each cell's rank."""
    width = max(1, int(ranks.max(initial=0)).bit_length())
    return [((ranks >> s) & 1).astype(bool) & present for s in range(width)]


def sliced_below(slices: list[np.ndarray], present: np.ndarray, bound: int) -> np.ndarray:
    """Cells whose rank is below bound: from the highest slice down, cells still equal so far and cells already less."""
    if bound >= 1 << len(slices):
        return present.copy()
    less, equal = np.zeros_like(present), present.copy()
    for s in reversed(range(len(slices))):
        if bound >> s & 1:
            less |= equal & ~slices[s]
            equal &= slices[s]
        else:
            equal &= ~slices[s]
    return less


def digits(ranks: np.ndarray, bases: tuple[int, ...]) -> list[np.ndarray]:
    """Components of a rank in mixed radix, the lowest first."""
    out, rest = [], ranks
    for b in bases:
        out.append(rest % b)
        rest = rest // b
    return out


def components_below(parts: list[list], present: np.ndarray, bases: tuple[int, ...], bound: int, read: Callable = lambda x: x) -> np.ndarray:
    """Multi-component index, parts[c][i] = cells whose component c is at most i (range encoded), or what read() makes
    them from: cells of rank < bound."""
    if bound >= np.prod(bases):
        return present.copy()
    want, rest = [], bound
    for b in bases:
        want.append(rest % b)
        rest //= b
    less, equal = np.zeros_like(present), present.copy()
    for c in reversed(range(len(bases))):
        at_most = lambda i, c=c: np.zeros_like(present) if i < 0 else present if i >= bases[c] - 1 else read(parts[c][i])
        less |= equal & at_most(want[c] - 1)
        equal &= at_most(want[c]) & ~at_most(want[c] - 1)
    return less
