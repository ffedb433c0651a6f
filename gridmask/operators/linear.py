"""Chunk coordinates, cell numbers and space-filling orders as Column expressions."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from itertools import accumulate

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import ArraySpec


#: Entries of a table that spreads digits over a Z code.
MOST_SPREAD = 256


def int_div(c: Column, k: int) -> Column:
    return F.floor(c / F.lit(k)).cast("long") if k > 1 else c


def chunk_coords(spec: ArraySpec) -> list[Column]:
    return [int_div(F.col(d.name) - F.lit(d.lo), s) for d, s in zip(spec.dims, spec.chunk)]


def local_coords(spec: ArraySpec) -> list[Column]:
    """Coordinates within the chunk, so that one dimension index serves every chunk."""
    return [(F.col(d.name) - F.lit(d.lo)) % F.lit(s) for d, s in zip(spec.dims, spec.chunk)]


def row_major(coords: Sequence[Column], shape: Sequence[int], pad: int = 1) -> Column:
    """Position in a row-major array; each row of the last dimension may be stretched to a multiple of `pad`."""
    shape = [*shape[:-1], -(-shape[-1] // pad) * pad]
    return reduce(lambda acc, x: acc * F.lit(x[1]) + x[0], zip(coords[1:], shape[1:]), coords[0]).cast("long")


def with_chunks(cells: DataFrame, spec: ArraySpec) -> DataFrame:
    """chunk_coord, offset and end (clipped by the array's shape), and cell_no in the full chunk shape."""
    c = chunk_coords(spec)
    lo = [F.lit(d.lo) + x * F.lit(s) for x, d, s in zip(c, spec.dims, spec.chunk)]
    hi = [F.least(x + F.lit(s), F.lit(d.hi)) for x, d, s in zip(lo, spec.dims, spec.chunk)]
    return cells.withColumns({"chunk_coord": F.array(*c), "offset": F.array(*lo), "end": F.array(*hi), "cell_no": row_major(local_coords(spec), spec.chunk)})


def with_irregular_chunks(cells: DataFrame, cuts: dict[str, Sequence[int]]) -> DataFrame:
    """chunk_coord from ascending lower cuts by dimension: the number of cuts at or below the coordinate, less one."""
    def below(d: str, xs: Sequence[int]) -> Column:
        return F.size(F.filter(F.array(*[F.lit(int(x)) for x in xs]), lambda e: e <= F.col(d))) - 1

    at = [below(d, xs) for d, xs in cuts.items()]
    return cells.withColumn("chunk_coord", F.array(*[a.cast("long") for a in at]))


def places(bits: Sequence[int]) -> list[list[int]]:
    """Place of bit j of each dimension in an interleaved code: bit by bit, of the dimensions that have it the last first."""
    out: list[list[int]] = [[] for _ in bits]
    at = 0
    for j in range(max(bits)):
        for d in reversed(range(len(bits))):
            if bits[d] > j:
                out[d].append(at)
                at += 1
    return out


def _each(bits: int | Sequence[int], n: int) -> Sequence[int]:
    return [bits] * n if isinstance(bits, int) else bits


def interleave(coords: Sequence[Column], bits: int | Sequence[int]) -> Column:
    """Z-order code of coordinates of so many bits, of each dimension its own if several are given."""
    parts = []
    for c, own in zip(coords, places(_each(bits, len(coords)))):
        for j, at in enumerate(own):
            parts.append(F.shiftleft(F.shiftright(c.cast("long"), j).bitwiseAND(F.lit(1).cast("long")), at))
    return reduce(lambda a, b: a.bitwiseOR(b), parts)


def deinterleave(z: Column, n: int, bits: int | Sequence[int]) -> list[Column]:
    return [reduce(lambda a, b: a.bitwiseOR(b), [F.lit(0).cast("long")] if not own else [F.shiftleft(F.shiftright(z, at).bitwiseAND(F.lit(1).cast("long")), j) for j, at in enumerate(own)]) for own in places(_each(bits, n))]


#: Bits that a Z code may have.
MOST_BITS = 62

#: Bits of each dimension's digit, for each level of a tree from the leaves up.
Layout = Sequence[Sequence[int]]


def code_layout(grid: Sequence[int], fanout: Sequence[int], levels: int) -> Layout:
    """The same bits on every level where the code fits; else a dimension whose nodes already span it has no bits from there
    up, since its digits are 0."""
    own = own_bits(fanout)
    if levels * sum(own) <= MOST_BITS:
        return [own] * levels
    return [[b if f**k < g else 0 for b, f, g in zip(own, fanout, grid)] for k in range(levels)]


def bits_below(layout: Layout) -> list[int]:
    """For each level, bits of a leaf's code below a node's of that level; the last are all bits."""
    return list(accumulate(map(sum, layout), initial=0))


def z_code(coords: Sequence[Column], fanout: Sequence[int], levels: int, layout: Layout | None = None) -> Column:
    """Z code of a chunk in a tree: one group of interleaved digits for each level, the root's first. Each dimension's digits
    are spread over the code by tables for several levels at once, which keeps the expression small whatever the number of
    levels: one that is too long is not compiled."""
    layout, parts = layout or [own_bits(fanout)] * levels, []
    below = bits_below(layout)
    for d, (c, f) in enumerate(zip(coords, fanout)):
        used = sum(own[d] > 0 for own in layout)
        most = max(m for m in range(1, levels + 1) if m == 1 or f**m <= MOST_SPREAD)
        for k in range(0, used, most):
            table = [0]
            for j in range(k, min(k + most, used)):
                one = [sum(((x >> i) & 1) << p for i, p in enumerate(places(layout[j])[d])) for x in range(f)]
                table = [high << below[j] | low for high in one for low in table]
            spread = F.expr(f"array({', '.join(f'{x}L' for x in table)})")
            parts.append(F.element_at(spread, (_digits(c.cast("long"), f, k, len(table)) + 1).cast("int")))
    return reduce(lambda a, b: a.bitwiseOR(b), parts)


def _digits(c: Column, f: int, k: int, base: int) -> Column:
    """Digits from k on to base f of a number that is not negative, as a number below `base`, a power of f; by its bits where
    f is a power of two."""
    if f & (f - 1) == 0:
        return F.shiftright(c, k * (f.bit_length() - 1)).bitwiseAND(F.lit(base - 1).cast("long"))
    return int_div(c, f**k) % F.lit(base)


def own_bits(fanout: Sequence[int]) -> list[int]:
    """Bits of a digit of each dimension."""
    return [max(1, (f - 1).bit_length()) for f in fanout]


def digit_bits(fanout: Sequence[int]) -> int:
    """Bits of the widest digit."""
    return max(own_bits(fanout))


def step_bits(fanout: Sequence[int]) -> int:
    """Bits of a Z code for one level."""
    return sum(own_bits(fanout))


def z_parent(z: Column, fanout: Sequence[int]) -> Column:
    return F.shiftright(z, step_bits(fanout))


def slot_digits(fanout: Sequence[int]) -> list[tuple[int, ...]]:
    """Digits of the child slots, in row-major order."""
    return [tuple(int(x) for x in i) for i in np.ndindex(*fanout)]


def slot_z(fanout: Sequence[int], own: Sequence[int] | None = None) -> list[int]:
    """Interleaved digits of each slot. own: the level's bits; a slot with another digit than 0 in a dimension without bits
    has no child, and its code is that of the first slot alike in the others."""
    at = places(own or own_bits(fanout))
    return [sum(((x >> j) & 1) << p for x, own in zip(digits, at) for j, p in enumerate(own)) for digits in slot_digits(fanout)]


def decode_z(z: int | np.ndarray, fanout: Sequence[int], levels: int, layout: Layout | None = None) -> list:
    """Chunk coordinates of a Z code of `levels` groups, or of an array of them."""
    layout = layout or [own_bits(fanout)] * levels
    below = bits_below(layout)
    out = [z & 0] * len(fanout)
    for k in reversed(range(levels)):
        at, group = places(layout[k]), (z >> below[k]) & ((1 << sum(layout[k])) - 1)
        for d, f in enumerate(fanout):
            out[d] = out[d] * f + sum(((group >> p) & 1) << j for j, p in enumerate(at[d]))
    return out


def hilbert_index(points: np.ndarray, bits: int) -> np.ndarray:
    """Distance along the Hilbert curve of points (rows, n) in [0, 2^bits)^n, by transposed Gray-code coordinates."""
    x = points.T.astype(np.int64).copy()
    n = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(n):
            high = (x[i] & q) > 0
            swap = np.where(high, 0, (x[0] ^ x[i]) & p)
            x[0] ^= np.where(high, p, 0)
            x[0] ^= swap
            x[i] ^= swap
        q >>= 1
    for i in range(1, n):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        t ^= np.where(x[n - 1] & q, q - 1, 0)
        q >>= 1
    x ^= t
    out = np.zeros_like(x[0])
    for j in reversed(range(bits)):
        for i in range(n):
            out = (out << 1) | ((x[i] >> j) & 1)
    return out


def hilbert_code(coords: Sequence[Column], bits: int) -> Column:
    """The order that keeps neighbours closest, for comparison: it has no common dimension masks over levels."""

    @F.pandas_udf("long")
    def run(*cols: pd.Series) -> pd.Series:
        return pd.Series(hilbert_index(np.stack([c.to_numpy(np.int64) for c in cols], axis=1), bits))

    return run(*coords)


def chunk_synopsis(cells: DataFrame, spec: ArraySpec, histogram: int = 0) -> DataFrame:
    """Non-empty cells, least and largest value of each chunk: partial sums before one small shuffle. With histogram, an
    array of the cells in so many equal intervals of the chunk's range, by a second aggregate of the same kind."""
    c = chunk_coords(spec)
    named = cells.withColumns({f"c{i}": x for i, x in enumerate(c)})
    keys = [f"c{i}" for i in range(spec.n)]
    synopsis = named.groupBy(*keys).agg(F.count("*").alias("n_cells"), F.min(spec.attr).alias("vmin"), F.max(spec.attr).alias("vmax"))
    if not histogram:
        return synopsis
    at = F.floor((F.col(spec.attr) - F.col("vmin")) * histogram / F.nullif(F.col("vmax") - F.col("vmin"), F.lit(0.0)))
    binned = named.join(synopsis, keys).withColumn("at", F.coalesce(F.least(at, F.lit(histogram - 1)), F.lit(0)))
    counts = [F.count_if(F.col("at") == k) for k in range(histogram)]
    return binned.groupBy(*keys, "n_cells", "vmin", "vmax").agg(F.array(*counts).alias("histogram"))
