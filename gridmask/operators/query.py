"""Queries over the chunk-tree index: masks over children, descent by levels, leaf evaluation, estimates.

The descent reads only the nodes of its frontier. A frontier of at most `dense_rows` nodes is held by the driver, which
fetches those nodes and walks them in memory; a larger one stays a table in the shared folder, and a level is one job
whose masks are bitwise Column expressions over 64-bit words. What the descent found then says which parts and codes
of the leaves and of the cells are read, and each of these is read in one pass.

Rounding is outward for "partial or more" and inward for "complete", so bins that were merged cost more descents but
never a wrong row. A child is complete when its whole value range and box lie inside the query.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cache, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.codec import CODECS
from ..model import ArrayQuery, Constraint, Region, complete_query
from . import linear
from .encoding import bin_range
from .tree import Index, in_ranges, leaf_bins, merge_ranges, ragged, to_words, written

Words = list[Column]
#: Ranges of codes that a filter names; more are told by a join.
MOST_RANGES = 256
#: Bytes of leaf answers that may be broadcast.
MOST_BROADCAST = 32 << 20


def _and(a: Words, b: Words) -> Words:
    return [x.bitwiseAND(y) for x, y in zip(a, b)]


def _or(a: Words, b: Words) -> Words:
    return [x.bitwiseOR(y) for x, y in zip(a, b)]


def _not(a: Words) -> Words:
    return [F.bitwise_not(x) for x in a]


def _const(value: int, n: int) -> Words:
    return [F.lit(value).cast("long")] * n


# ---- attribute masks --------------------------------------------------------------------------------------------


def _present(n_words: int) -> Words:
    return [F.element_at("present", w + 1) for w in range(n_words)]


def below(v: Column, or_at: bool, n_words: int) -> Words:
    """Children that may have values below v (or_at: or at v): the set of the first threshold that covers them."""
    at = F.size(F.filter("plus", lambda t: t <= v if or_at else t < v))
    row = F.when(at < F.size("plus"), F.element_at("started", F.least(at, F.size("plus") - 1) + 1))
    none = v < F.col("vmin") if or_at else v <= F.col("vmin")
    return [F.when(none, F.lit(0).cast("long")).otherwise(F.coalesce(F.element_at(row, w + 1), p)) for w, p in enumerate(_present(n_words))]


def over(v: Column, or_at: bool, n_words: int) -> Words:
    """Children that surely have all values below v (or_at: or at v): the set of the last threshold that allows it."""
    at = F.size(F.filter("minus", lambda t: t <= v if or_at else t < v))
    row = F.when(at > 0, F.element_at("ended", F.greatest(at, F.lit(1))))
    return [F.coalesce(F.element_at(row, w + 1), F.lit(0).cast("long")) for w in range(n_words)]


def holding(v: Column, n_words: int) -> Words:
    """Children that may hold the value v, from the equality bitmaps."""
    by_value = F.size("edges") == F.size("weights")
    inside = F.least(F.size(F.filter("edges", lambda e: e <= v)), F.size("equal"))
    at = F.when(by_value, F.array_position("edges", v)).when((v >= F.col("vmin")) & (v <= F.col("vmax")), inside).otherwise(F.lit(0))
    row = F.when(at > 0, F.element_at("equal", F.greatest(at, F.lit(1)).cast("int")))
    return [F.coalesce(F.element_at(row, w + 1), F.lit(0).cast("long")) for w in range(n_words)]


def is_point(c: Constraint) -> bool:
    return c.lo is not None and c.lo == c.hi and c.lo_incl and c.hi_incl


def attr_partial(c: Constraint, lo: Column | None, hi: Column | None, n_words: int) -> Words:
    """Children whose value range may meet the constraint: begun by its upper bound and not ended before its lower. A
    single value is told by the equality bitmaps as well."""
    out = _present(n_words) if hi is None else below(hi, c.hi_incl, n_words)
    if lo is not None:
        out = _and(out, _not(over(lo, not c.lo_incl, n_words)))
    return _and(out, holding(lo, n_words)) if is_point(c) else out


def attr_complete(c: Constraint, lo: Column | None, hi: Column | None, n_words: int) -> Words:
    """Children whose value range surely lies inside: not begun below the lower bound, ended by the upper."""
    out = _present(n_words)
    if lo is not None:
        out = _and(out, _not(below(lo, not c.lo_incl, n_words)))
    if hi is not None:
        out = _and(out, over(hi, c.hi_incl, n_words))
    return out


# ---- dimension masks --------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class DimMasks:
    """The same for all nodes: for each dimension and bucket the slots at, from and up to the bucket."""

    fanout: tuple[int, ...]
    n_words: int
    at: list[list[list[int]]]
    from_: list[list[list[int]]]
    upto: list[list[list[int]]]

    @property
    def ints(self) -> dict[str, list[list[int]]]:
        """The same masks as whole numbers."""
        return _ints(self.fanout)


@cache
def _ints(fanout: tuple[int, ...]) -> dict[str, list[list[int]]]:
    m = dim_masks(fanout)
    joined = lambda words: sum((w & ((1 << 64) - 1)) << (64 * i) for i, w in enumerate(words))
    return {k: [[joined(w) for w in rows] for rows in getattr(m, k)] for k in ("at", "from_", "upto")}


@cache
def dim_masks(fanout: tuple[int, ...]) -> DimMasks:
    digits = np.array(linear.slot_digits(fanout))
    n = len(digits)
    rows: dict[str, list] = {"at": [], "from_": [], "upto": []}
    for d, f in enumerate(fanout):
        rows["at"].append([to_words(digits[:, d] == b, n) for b in range(f)])
        rows["from_"].append([to_words(digits[:, d] >= b, n) for b in range(f)])
        rows["upto"].append([to_words(digits[:, d] <= b, n) for b in range(f)])
    return DimMasks(fanout, -(-n // 64), **rows)


def _table(rows: list[list[int]], i: Column, n_words: int) -> Words:
    literal = ", ".join(f"array({', '.join(f'{w}L' for w in r)})" for r in rows)
    row = F.element_at(F.expr(f"array({literal})"), i.cast("int") + 1)
    return [F.element_at(row, w + 1) for w in range(n_words)]


def dim_match(m: DimMasks, d: int, lo: Column, hi: Column, node_lo: Column, span: int, domain_hi: int, exact: bool) -> tuple[Words, Words]:
    """(touched, cut) slots along dimension d by the run [lo, hi). cut: a bound falls into the slot; in bucket form also
    when it only lies on its border, which exact avoids."""
    f = m.fanout[d]
    bucket = lambda x: F.greatest(F.lit(0), F.least(F.floor((x - node_lo) / F.lit(span)), F.lit(f - 1)))
    node_hi = F.least(node_lo + F.lit(span * f), F.lit(domain_hi))
    meets = (lo < node_hi) & (hi > node_lo)
    zero = _const(0, m.n_words)
    low, high = bucket(lo), bucket(hi - 1)
    touched = [F.when(meets, a.bitwiseAND(b)).otherwise(z) for a, b, z in zip(_table(m.from_[d], low, m.n_words), _table(m.upto[d], high, m.n_words), zero)]
    low_in = (lo > node_lo) & (((lo - node_lo) % F.lit(span) != 0) if exact else F.lit(True))
    high_in = (hi < node_hi) & (((hi - node_lo) % F.lit(span) != 0) if exact else F.lit(True))
    at_low = [F.when(low_in, a).otherwise(z) for a, z in zip(_table(m.at[d], low, m.n_words), zero)]
    at_high = [F.when(high_in, a).otherwise(z) for a, z in zip(_table(m.at[d], high, m.n_words), zero)]
    return touched, _and(_or(at_low, at_high), touched)


# ---- descent ----------------------------------------------------------------------------------------------------


def _literal_bounds(c: Constraint) -> tuple[Column | None, Column | None]:
    return (None if c.lo is None else F.lit(float(c.lo)), None if c.hi is None else F.lit(float(c.hi)))


def node_masks(index: Index, region: Region, level: int, exact: bool) -> tuple[Words, Words]:
    """(complete, partial) words over the children of a level-`level` node row."""
    m = dim_masks(index.fanout)
    spans = index.child_span(level)
    cover: Words | None = None
    full: Words | None = None
    for d, runs in enumerate(region.dims):
        node_lo = F.element_at("lo", d + 1)
        pairs = [dim_match(m, d, F.lit(a), F.lit(b), node_lo, spans[d], index.spec.dims[d].hi, exact) for a, b in runs]
        touched = reduce(_or, [t for t, _ in pairs])
        whole = reduce(_or, [_and(t, _not(c)) for t, c in pairs])
        cover = touched if cover is None else _and(cover, touched)
        full = whole if full is None else _and(full, whole)
    some = reduce(_or, [attr_partial(c, *_literal_bounds(c), m.n_words) for c in region.attr])
    all_ = reduce(_or, [attr_complete(c, *_literal_bounds(c), m.n_words) for c in region.attr])
    complete = _and(all_, full)
    return complete, _and(_and(_or(some, all_), cover), _not(complete))


def set_slots(words: str, fanout: tuple[int, ...]) -> Column:
    """Slots whose bit is set in an array of words."""
    n = int(np.prod(fanout))
    return F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda s: F.getbit(F.element_at(words, (s / 64).cast("int") + 1), s % 64) == 1)


def disjoint(region: Region) -> Column:
    """Node whose value range meets no range of the query: rejected before any mask is read."""
    meets = F.lit(False)
    for c in region.attr:
        ok = F.lit(True)
        if c.hi is not None:
            ok = ok & (F.col("vmin") <= F.lit(float(c.hi)) if c.hi_incl else F.col("vmin") < F.lit(float(c.hi)))
        if c.lo is not None:
            ok = ok & (F.col("vmax") >= F.lit(float(c.lo)) if c.lo_incl else F.col("vmax") > F.lit(float(c.lo)))
        meets = meets | ok
    return ~meets


def expand(rows: DataFrame, index: Index, level: int, complete: Words, partial: Words, keep: tuple[str, ...] = ()) -> DataFrame:
    """Child Z codes with their status, from rows of nodes of the level."""
    zs = F.expr(f"array({', '.join(f'{x}L' for x in linear.slot_z(index.fanout, index.layout[level - 1]))})")
    marked = rows.select(*keep, "z", F.array(*complete).alias("c"), F.array(*partial).alias("p"))
    status = lambda name, flag: F.transform(set_slots(name, index.fanout), lambda s: F.struct(s.alias("slot"), F.lit(flag).alias("complete")))
    kids = marked.select(*keep, "z", F.explode(F.concat(status("c", True), status("p", False))).alias("k"))
    return kids.select(*keep, F.shiftleft("z", index.bits(level, level - 1)).bitwiseOR(F.element_at(zs, F.col("k.slot") + 1)).alias("z"), F.col("k.complete").alias("complete"))


def dense_masks(row: dict, region: Region, m: DimMasks, spans: list[int], domain: list[int], exact: bool) -> tuple[int, int]:
    """node_masks for one node in memory, on whole-number bitmaps: (complete, partial)."""
    present, plus, minus, edges = row["present"], row["plus"], row["minus"], row["edges"]

    def begun(v: float, or_at: bool) -> int:
        if v < row["vmin"] or v == row["vmin"] and not or_at:
            return 0
        i = bisect_right(plus, v) if or_at else bisect_left(plus, v)
        return row["started"][i] if i < len(plus) else present

    def ended(v: float, or_at: bool) -> int:
        i = bisect_right(minus, v) if or_at else bisect_left(minus, v)
        return row["ended"][i - 1] if i else 0

    def equal(v: float) -> int:
        i = bisect_right(edges, v) - 1
        if row["by_value"]:
            return row["equal"][i] if i >= 0 and edges[i] == v else 0
        return row["equal"][min(i, len(row["equal"]) - 1)] if row["vmin"] <= v <= row["vmax"] else 0

    some = all_ = 0
    for c in region.attr:
        may, whole = present, present
        if c.hi is not None:
            may = begun(c.hi, c.hi_incl)
            whole &= ended(c.hi, c.hi_incl)
        if c.lo is not None:
            may &= ~ended(c.lo, not c.lo_incl)
            whole &= ~begun(c.lo, not c.lo_incl)
        if is_point(c):
            may &= equal(c.lo)
        some, all_ = some | may, all_ | whole
    cover = full = present
    for d, runs in enumerate(region.dims):
        start, span, f = row["lo"][d], spans[d], m.fanout[d]
        end, touched, inside = min(start + span * f, domain[d]), 0, 0
        for a, b in runs:
            if a >= end or b <= start:
                continue
            low, high = max(0, (a - start) // span), min(f - 1, (b - 1 - start) // span)
            t, cut = m.ints["from_"][d][low] & m.ints["upto"][d][high], 0
            if a > start and not (exact and (a - start) % span == 0):
                cut |= m.ints["at"][d][low]
            if b < end and not (exact and (b - start) % span == 0):
                cut |= m.ints["at"][d][high]
            touched, inside = touched | t, inside | t & ~cut
        cover, full = cover & touched, full & inside
    complete = all_ & full
    return complete, (some | all_) & cover & ~complete


@dataclass
class Step:
    """Children found on one level: codes held by the driver, or a table (z, complete)."""

    level: int
    visited: int | None = None
    complete: list[int] | None = None
    partial: list[int] | None = None
    frame: DataFrame | None = None


@dataclass
class Found:
    """A descent's steps from the root's children down."""

    index: Index
    steps: list[Step] = field(default_factory=list)

    def kids(self, i: int) -> DataFrame:
        """(z, complete) of one step."""
        step = self.steps[i]
        if step.frame is not None:
            return step.frame
        zs = [*step.complete, *step.partial]
        flags = [True] * len(step.complete) + [False] * len(step.partial)
        return self.index.spark.createDataFrame(pa.table({"z": pa.array(zs, pa.int64()), "complete": pa.array(flags, pa.bool_())}))

    def __iter__(self) -> Iterator[tuple[int, DataFrame]]:
        return ((s.level, self.kids(i)) for i, s in enumerate(self.steps))

    @property
    def held(self) -> bool:
        """Everything is in the driver's memory."""
        return all(s.frame is None for s in self.steps)

    def partial(self) -> list[int] | None:
        """Codes of partial children on the last level, if few; each stands for one leaf when the descent is complete."""
        return self.steps[-1].partial

    def ranges(self) -> list[tuple[int, int]] | None:
        """Ranges of leaf codes that complete nodes cover, or None if those are in a table."""
        if not self.held:
            return None
        return merge_ranges([self.index.span(z, s.level) for s in self.steps for z in s.complete])

    def cover(self) -> list[tuple[int, int]] | None:
        """Ranges of leaf codes that hold all hits; of whole parts, where the codes are in a table."""
        if self.held:
            last = self.steps[-1]
            return merge_ranges([*self.ranges(), *(self.index.span(z, last.level) for z in last.partial)])
        index, parts = self.index, set()
        for i, (level, kids) in enumerate(self):
            if i + 1 < len(self.steps):
                kids = kids.where("complete")
            if level > index.part_level:  # a node above the parts covers several; those are few
                ranges = [index.span(r["z"], level) for r in kids.collect()]
                parts |= set(index.parts_in(merge_ranges(ranges))) if ranges else set()
            else:
                parts |= {r["p"] for r in kids.select(F.shiftright("z", index.bits(index.part_level, level)).alias("p")).distinct().collect()}
        return merge_ranges([(p << index.shift, (p + 1) << index.shift) for p in parts])


def descend(index: Index, region: Region, exact: bool = True, levels: int | None = None) -> Found:
    """From the root's children down to leaves, or `levels` steps."""
    found = Found(index)
    if region.empty:
        found.steps.append(Step(0, 0, [], []))
        return found
    held: list[int] | None = [0] if index.dense_rows else None
    frontier: DataFrame | None = None
    m = dim_masks(index.fanout)
    domain = [d.hi for d in index.spec.dims]
    for level in range(index.height, 0, -1):
        if levels is not None and len(found.steps) >= levels:
            break
        if held is not None:
            nodes = index.node_rows(level, held) if held else {}
            step = Step(level - 1, sum(z in nodes for z in held), [], [])
            zs, digit = linear.slot_z(index.fanout, index.layout[level - 1]), index.bits(level, level - 1)
            for z in held:
                row = nodes.get(z)
                if row is None or not any((c.hi is None or row["vmin"] <= c.hi) and (c.lo is None or row["vmax"] >= c.lo) for c in region.attr):
                    continue
                for bits, kids in zip(dense_masks(row, region, m, index.child_span(level), domain, exact), (step.complete, step.partial)):
                    while bits:
                        low = bits & -bits
                        kids.append(z << digit | zs[low.bit_length() - 1])
                        bits ^= low
            held = step.partial
            found.steps.append(step)
            if len(held) > index.dense_rows and level > 1:
                frontier, held = found.kids(-1), None
            continue
        if frontier is None:
            rows = index.level(level)
        else:
            above = found.cover() if level + 1 == index.height or not found.steps else _under(index, frontier, level)
            rows = index.read(f"level={level}", above).join(frontier.where(~F.col("complete")).select("z"), "z", "left_semi")
        # a frontier is small beside its level; written down, it is worked out once for all that follows
        kids = written(expand(rows.where(~disjoint(region)), index, level, *node_masks(index, region, level, exact)), "frontier")
        step = Step(level - 1, frame=kids)
        found.steps.append(step)
        frontier = kids
        if index.dense_rows:
            few = kids.where(~F.col("complete")).select("z").limit(index.dense_rows + 1).collect()
            if len(few) <= index.dense_rows:
                held = step.partial = sorted(r["z"] for r in few)
    return found


def _under(index: Index, frontier: DataFrame, level: int) -> list[tuple[int, int]]:
    """Ranges of leaf codes of the parts that partial nodes of `level` touch: as few rows as parts."""
    if level > index.part_level:
        return merge_ranges([(p << index.shift, (p + 1) << index.shift) for p in index.parts])
    parts = frontier.where(~F.col("complete")).select(F.shiftright("z", index.bits(index.part_level, level)).alias("p")).distinct().collect()
    return merge_ranges([(r["p"] << index.shift, (r["p"] + 1) << index.shift) for r in parts])


def complete_leaves(index: Index, found: Found, cover: list[tuple[int, int]]) -> DataFrame:
    """Z codes of all leaves under complete nodes: an equi-join on the prefix."""
    slim = index.read("level=0", cover).select("z")
    parts = []
    for level, kids in found:
        tops = kids.where("complete").select(F.col("z").alias("top"))
        parts.append(slim.join(tops, F.shiftright("z", index.bits(level)) == F.col("top"), "left_semi") if level else tops.withColumnRenamed("top", "z"))
    return reduce(DataFrame.union, parts)


def leaf_answers(index: Index, region: Region, found: Found, cover: list[tuple[int, int]] | None = None) -> DataFrame:
    """(z, listed, hit, sure, reads): for each partial leaf the words of its cells in the region, those of them that need no
    look at their value, and the number of bitmaps read. Of a listed leaf the numbers of the cells: they are few."""
    spec, cfg, runs, ranges_ = index.spec, index.config, region.dims, region.attr
    n_words = -(-spec.chunk_cells // 64)
    held = found.partial()
    if held is not None:
        rows = index.read("level=0", merge_ranges([(z, z + 1) for z in held])) if held else index.leaves
        rows = rows.where(F.expr(f"z IN ({', '.join(f'{z}L' for z in held)})") if held else F.lit(False))
    else:
        rows = index.read("level=0", cover if cover is not None else found.cover()).join(found.kids(-1).where(~F.col("complete")).select("z"), "z", "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            short = b.column("kind").to_numpy(zero_copy_only=False) == "list"
            if short.any():
                yield listed_answers(b.filter(pa.array(short)), runs, ranges_, spec.chunk)
            if short.all():
                continue
            zs, words, reads = [], ([], []), []
            for row in b.filter(pa.array(~short)).to_pylist():
                hit, sure, n = evaluate_leaf(row, runs, ranges_, spec.chunk, cfg.leaf_encoding, cfg.codec)
                if hit.any():
                    zs.append(row["z"])
                    reads.append(n)
                    for out, mask in zip(words, (hit, sure)):
                        padded = np.zeros(n_words * 64, bool)
                        padded[: len(mask)] = mask
                        out.append(np.packbits(padded, bitorder="little").view("<i8"))
            at = pa.array(np.arange(len(zs) + 1, dtype=np.int32) * n_words)
            lists = [pa.ListArray.from_arrays(at, pa.array(np.concatenate(w) if w else np.zeros(0, np.int64))) for w in words]
            yield pa.RecordBatch.from_arrays([pa.array(zs, pa.int64()), pa.array(np.zeros(len(zs), bool)), *lists, pa.array(reads, pa.int32())], names=["z", "listed", "hit", "sure", "reads"])

    slim = rows.select("z", "lo", "edges", "kind", "present", "bitmaps", "list_no", "list_value")
    return slim.mapInArrow(run, "z long, listed boolean, hit array<long>, sure array<long>, reads int")


def listed_answers(b: pa.RecordBatch, runs, ranges_: tuple[Constraint, ...], shape: tuple[int, ...]) -> pa.RecordBatch:
    """Answers of listed leaves, all at once."""
    no, v = b.column("list_no").flatten().to_numpy(), b.column("list_value").flatten().to_numpy()
    leaf = np.repeat(np.arange(b.num_rows), np.diff(b.column("list_no").offsets.to_numpy()))
    lo = b.column("lo").flatten().to_numpy().reshape(b.num_rows, len(shape))
    hit = np.logical_or.reduce([holds(c, v) for c in ranges_])
    for d, (own, local) in enumerate(zip(runs, np.unravel_index(no, shape))):
        starts, ends = np.array(sorted(own)).T
        at = lo[leaf, d] + local
        k = np.searchsorted(starts, at, side="right") - 1
        hit &= (k >= 0) & (at < ends[k])
    count = np.bincount(leaf[hit], minlength=b.num_rows)
    some = count > 0
    places = ragged(count[some], no[hit].astype(np.int64), pa.int64())
    return pa.RecordBatch.from_arrays([b.column("z").filter(pa.array(some)), pa.array(some[some]), places, places, pa.array(np.zeros(some.sum(), np.int32))], names=["z", "listed", "hit", "sure", "reads"])


def bit(words: str, place: str) -> Column:
    return F.getbit(F.element_at(words, (F.col(place) / 64).cast("int") + 1), F.col(place) % 64) == 1


def told(name: str) -> Column:
    """A cell is among those of its leaf's answer."""
    return F.when(F.col("listed"), F.array_contains(name, F.col("cell_no").cast("long"))).otherwise(bit(name, "cell_no"))


def cells_of(name: str) -> Column:
    """How many cells a leaf's answer names."""
    return F.when(F.col("listed"), F.size(name)).otherwise(F.aggregate(name, F.lit(0), lambda a, w: a + F.bit_count(w)))


@cache
def line_masks(shape: tuple[int, ...]) -> tuple[list[np.ndarray], list[np.ndarray]] | None:
    """For each dimension of a chunk (values, cells): the cells at each local coordinate, and those up to it. The same
    for every chunk; None where chunks are too large for so many masks."""
    cells = int(np.prod(shape))
    if cells * sum(shape) > 1 << 24:
        return None
    local = np.indices(shape).reshape(len(shape), -1)
    at = [local[d][None] == np.arange(s)[:, None] for d, s in enumerate(shape)]
    return at, [np.logical_or.accumulate(a, axis=0) for a in at]


def local_mask(lo: list[int], runs, shape: tuple[int, ...]) -> np.ndarray:
    """Cells of a chunk inside the runs: a run is the difference of two masks, a single coordinate is one mask."""
    masks = line_masks(tuple(shape))
    out: np.ndarray | None = None
    for d, (start, own) in enumerate(zip(lo, runs)):
        if masks is None:
            flat = np.zeros(shape[d], bool)
            for a, b in own:
                flat[max(0, a - start) : max(0, b - start)] = True
            line = np.broadcast_to(flat.reshape([-1 if k == d else 1 for k in range(len(shape))]), shape).ravel()
        else:
            line = np.zeros(masks[0][d].shape[1], bool)
            for a, b in own:
                a, b = max(a - start, 0), min(b - start, shape[d])
                if b - a == 1:
                    line = line | masks[0][d][a]
                elif b > a:
                    line = line | (masks[1][d][b - 1] & ~masks[1][d][a - 1] if a else masks[1][d][b - 1])
        out = line if out is None else out & line
    return out


def evaluate_leaf(row: dict, runs, ranges_: tuple[Constraint, ...], shape, encoding: str, codec: str) -> tuple[np.ndarray, np.ndarray, int]:
    """(hit, sure, bitmaps read) over the cells of a leaf of bitmaps: bins inside a range are sure, at most two edge bins are not."""
    inside = local_mask(row["lo"], runs, shape)
    decode = CODECS[codec].decode
    bitmaps, opened = row["bitmaps"], {}

    def read(k: int) -> np.ndarray:
        if k not in opened:
            opened[k] = decode(bitmaps[k])
        return opened[k]

    present = decode(row["present"])
    edges, by_value = np.array(row["edges"]), row["kind"] == "values"
    bins = leaf_bins(edges, by_value)
    sure, maybe = np.zeros_like(present), np.zeros_like(present)
    for c in ranges_:
        first, last, first_sure, last_sure = bin_span(c, edges, bins, by_value)
        if first > last:
            continue
        outer, _ = bin_range(read, present, bins, encoding, first, last)
        sure |= outer if (first_sure, last_sure) == (first, last) else bin_range(read, present, bins, encoding, first_sure, last_sure)[0]
        maybe |= outer
    hit = maybe & inside
    return hit, sure & hit, len(opened)


def holds(c: Constraint, v: np.ndarray) -> np.ndarray:
    out = np.ones(len(v), bool)
    if c.lo is not None:
        out &= v >= c.lo if c.lo_incl else v > c.lo
    if c.hi is not None:
        out &= v <= c.hi if c.hi_incl else v < c.hi
    return out


def bin_span(c: Constraint, edges: np.ndarray, bins: int, by_value: bool) -> tuple[int, int, int, int]:
    """First and last bin that a range meets, and first and last that lie inside it."""
    if by_value:
        ok = np.flatnonzero(holds(c, edges))
        return (int(ok[0]), int(ok[-1]), int(ok[0]), int(ok[-1])) if len(ok) else (0, -1, 0, -1)
    lows, highs = (edges[:-1], edges[1:]) if len(edges) > 1 else (edges, edges)
    closed = np.arange(bins) == bins - 1  # the last bin holds its upper edge
    meets, inside = np.ones(bins, bool), np.ones(bins, bool)
    if c.lo is not None:
        meets &= (highs > c.lo) | (closed & (highs == c.lo) & c.lo_incl)
        inside &= lows >= c.lo if c.lo_incl else lows > c.lo
    if c.hi is not None:
        meets &= lows <= c.hi if c.hi_incl else lows < c.hi
        inside &= (highs <= c.hi) & (~closed | (highs < c.hi) | c.hi_incl)
    m, s = np.flatnonzero(meets), np.flatnonzero(meets & inside)
    if not len(m):
        return 0, -1, 0, -1
    return (int(m[0]), int(m[-1]), int(s[0]), int(s[-1])) if len(s) else (int(m[0]), int(m[-1]), 1, 0)


def tagged_cells(index: Index, region: Region, found: Found) -> DataFrame:
    """The cells that may be hits, read once: the array's columns, level (of the complete node that holds the cell; null
    if its leaf is partial), listed, hit and sure (a partial leaf's answer), z and cell_no."""
    cover = found.cover()
    cells = index.read("cells", cover)
    answers = leaf_answers(index, region, found, cover).select("z", "listed", "hit", "sure")
    held, whole = found.partial(), found.ranges()
    small = held is not None and len(held) * index.spec.chunk_cells // 4 <= MOST_BROADCAST
    if whole is not None and len(whole) <= MOST_RANGES:
        if not held and held is not None:
            return cells.where(in_ranges("z", whole)).withColumns({"complete": F.lit(True), "listed": F.lit(None).cast("boolean"), "hit": F.lit(None).cast("array<long>"), "sure": F.lit(None).cast("array<long>")})
        joined = cells.join(F.broadcast(answers) if small else answers, "z", "left").withColumn("complete", in_ranges("z", whole))
        return joined.where(F.col("complete") | F.col("hit").isNotNull())
    none = F.lit(None).cast("array<long>")
    tags = answers.withColumn("complete", F.lit(False)).unionByName(complete_leaves(index, found, cover).select("z", F.lit(None).cast("boolean").alias("listed"), none.alias("hit"), none.alias("sure"), F.lit(True).alias("complete")))
    return cells.join(tags, "z")


def verified(index: Index, region: Region) -> Column:
    """A tagged cell is a hit."""
    value = F.col(index.spec.attr)
    holds_ = reduce(lambda a, b: a | b, [c.column(value) for c in region.attr])
    return F.col("complete") | (F.coalesce(told("hit"), F.lit(False)) & (told("sure") | holds_))


def region_predicate(region: Region, index: Index) -> Column:
    """The region as a plain predicate on a cell. Runs over a dimension's whole domain are left out."""
    out = F.lit(True)
    for dim, runs in zip(index.spec.dims, region.dims):
        if runs != ((dim.lo, dim.hi),):
            out = out & in_ranges(dim.name, list(runs))
    return out & reduce(lambda a, b: a | b, [c.column(F.col(index.spec.attr)) for c in region.attr])


def range_query(index: Index, q: ArrayQuery | Region, exact: bool = True, leaves: str = "values") -> DataFrame:
    """The cells that satisfy the query, with the array's columns. Sets of values and of coordinates are allowed.

    leaves: how cells of partial leaves are told. "values": by the cells themselves, which the answer reads anyway; the
    plan is then one scan of the parts and codes that the descent left, with a filter that Parquet sees too. "bitmaps":
    by the leaves' bitmaps, and by values only where an edge bin leaves it open, as in count_query, which reads no other
    cells.
    """
    region = q if isinstance(q, Region) else complete_query(q, index.spec)
    cols = [*index.spec.names, index.spec.attr]
    if region.empty:
        return index.cells.select(*cols).limit(0)
    found = descend(index, region, exact)
    if leaves == "values":
        return index.read("cells", found.cover()).where(region_predicate(region, index)).select(*cols)
    return tagged_cells(index, region, found).where(verified(index, region)).select(*cols)


def count_query(index: Index, q: ArrayQuery | Region, exact: bool = True) -> DataFrame:
    """One row: hits. Complete nodes count by their synopses, partial leaves by their bitmaps; cells are read only for
    leaves whose edge bins leave some open."""
    region = q if isinstance(q, Region) else complete_query(q, index.spec)
    if region.empty:
        return index.spark.createDataFrame([(0,)], "hits long")
    found = descend(index, region, exact)
    whole = []
    for level, kids in found:
        whole.append(index.level(level).join(kids.where("complete").select("z"), "z", "left_semi").select(F.col("n_cells").alias("n")))
    answers = written(leaf_answers(index, region, found), "leaf-answers")
    sure = answers.select(cells_of("sure").cast("long").alias("n"))
    open_ = answers.where(cells_of("hit") > cells_of("sure")).select("z", "listed", "hit", "sure")
    value = reduce(lambda a, b: a | b, [c.column(F.col(index.spec.attr)) for c in region.attr])
    looked = index.read("cells", found.cover()).join(open_, "z").where(told("hit") & ~told("sure") & value)
    return reduce(DataFrame.union, [*whole, sure, looked.select(F.lit(1).cast("long").alias("n"))]).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("hits"))


def member_query(index: Index, dims: dict[str, list[int]] | None = None, values: list[float] | None = None, leaves: str = "bitmaps") -> DataFrame:
    """Sets of coordinates and of values: by the equality bitmaps of nodes and the coordinate masks of chunks."""
    attr = Constraint() if values is None else Constraint.isin(values)
    return range_query(index, ArrayQuery({d: Constraint.isin(v) for d, v in (dims or {}).items()}, attr), leaves=leaves)


def range_query_multi(parts: list[tuple[str, Index, ArrayQuery]]) -> DataFrame:
    """Constraints on several attributes of one array, (name of the attribute's column, its index, query): an index each,
    results meet on the coordinates."""
    out: DataFrame | None = None
    for name, index, q in parts:
        hits = range_query(index, q).withColumnRenamed(index.spec.attr, name)
        out = hits if out is None else out.join(hits, index.spec.names)
    return out


def batch_query(index: Index, queries: DataFrame) -> DataFrame:
    """Many range queries in one plan. queries: q, lo_<dim>, hi_<dim> (exclusive), lo_value, hi_value, and if wanted
    booleans lo_incl and hi_incl for the values (missing: the lower bound is inclusive, the upper is not). A null bound
    is open.

    The queries run along in the frontier, so a node is read once for all of them; in the end each cell meets the
    queries that reach its leaf, in one pass over the cells of the parts that any query reaches.
    """
    spec, m = index.spec, dim_masks(index.fanout)
    open_ = {"lo_value": float("-inf"), "hi_value": float("inf")} | {f"lo_{d.name}": d.lo for d in spec.dims} | {f"hi_{d.name}": d.hi for d in spec.dims}
    asked = queries.select("q", *[F.coalesce(F.col(k), F.lit(v)).alias(k) for k, v in open_.items()], *[F.coalesce(F.col(k), F.lit(v)).alias(k) if k in queries.columns else F.lit(v).alias(k) for k, v in (("lo_incl", True), ("hi_incl", False))])
    # an open end takes in infinite values too
    asked = asked.withColumn("hi_incl", F.col("hi_incl") | (F.col("hi_value") == float("inf")))
    names = [c for c in asked.columns if c != "q"]
    # a bound that is not as usual moves to the next number, so that masks need one form
    frontier = asked.select("q", *names, F.lit(0).cast("long").alias("z"), F.lit(False).alias("complete"))
    keep, whole = ("q", *names), []
    for level in range(index.height, 0, -1):
        rows = index.level(level).join(frontier.where(~F.col("complete")).drop("complete"), "z").where("vmin <= hi_value and vmax >= lo_value")
        cover: Words | None = None
        cut: Words | None = None
        for d, dim in enumerate(spec.dims):
            t, k = dim_match(m, d, F.col(f"lo_{dim.name}"), F.col(f"hi_{dim.name}"), F.element_at("lo", d + 1), index.child_span(level)[d], dim.hi, True)
            cover, cut = (t, k) if cover is None else (_and(cover, t), _or(cut, k))
        lo, hi = F.col("lo_value"), F.col("hi_value")

        def either(flag: str, f) -> Words:
            return [F.when(F.col(flag), a).otherwise(b) for a, b in zip(f(True), f(False))]  # noqa: B023

        begun = either("hi_incl", lambda x: below(hi, x, m.n_words))  # noqa: B023
        out = either("lo_incl", lambda x: over(lo, not x, m.n_words))  # noqa: B023
        all_ = _and(_and(_present(m.n_words), _not(either("lo_incl", lambda x: below(lo, not x, m.n_words)))), either("hi_incl", lambda x: over(hi, x, m.n_words)))  # noqa: B023
        complete = _and(_and(all_, cover), _not(cut))
        partial = _and(_and(_or(_and(begun, _not(out)), all_), cover), _not(complete))
        frontier = expand(rows, index, level, complete, partial, keep)
        done = frontier.where("complete").select("q", F.col("z").alias("top"))
        slim = index.read("level=0").select("z")
        whole.append((slim.join(done, F.shiftright("z", index.bits(level - 1)) == F.col("top")) if level > 1 else done.withColumnRenamed("top", "z")).select("q", "z", F.lit(True).alias("complete"), *[F.lit(None).cast(dict(asked.dtypes)[n]).alias(n) for n in names]))
    tags = reduce(DataFrame.unionByName, [*whole, frontier.where(~F.col("complete")).select("q", "z", "complete", *names)])
    value = F.col(spec.attr)
    inside = reduce(lambda a, b: a & b, [(F.col(d) >= F.col(f"lo_{d}")) & (F.col(d) < F.col(f"hi_{d}")) for d in spec.names])
    inside = inside & ((value > F.col("lo_value")) | (F.col("lo_incl") & (value == F.col("lo_value")))) & ((value < F.col("hi_value")) | (F.col("hi_incl") & (value == F.col("hi_value"))))
    # what the descent found is written down; of the cells only the parts that it reached are read
    tags = written(tags, "tags")
    parts = sorted(r["p"] for r in tags.select(F.shiftright("z", index.shift).alias("p")).distinct().collect())
    cells = index.read("cells", merge_ranges([(p << index.shift, (p + 1) << index.shift) for p in parts]))
    return cells.join(tags, "z").where(F.col("complete") | inside).select("q", *spec.names, spec.attr)


# ---- estimates, progress, counters ------------------------------------------------------------------------------


def estimate_count(index: Index, q: ArrayQuery, levels: int) -> DataFrame:
    """One row: lower and upper bound of the number of hits after `levels` steps from the root."""
    region = complete_query(q, index.spec)
    found = descend(index, region, levels=levels)
    parts = []
    for i, (level, kids) in enumerate(found):
        own = kids if i == len(found.steps) - 1 else kids.where("complete")
        parts.append(index.level(level).select("z", "n_cells").join(own, "z").select("n_cells", "complete"))
    both = reduce(DataFrame.union, parts)
    lower = F.coalesce(F.sum(F.when(F.col("complete"), F.col("n_cells"))), F.lit(0)).alias("lower_bound")
    return both.agg(lower, F.coalesce(F.sum("n_cells"), F.lit(0)).alias("upper_bound"))


def _overlap(c: Constraint, a: Column, b: Column) -> Column:
    """Share of the values of a bin [a, b] that a range takes, spread evenly; a bin of one value is in it or not."""
    lo = F.lit(float("-inf") if c.lo is None else float(c.lo))
    hi = F.lit(float("inf") if c.hi is None else float(c.hi))
    return F.when(a == b, c.column(a).cast("double")).otherwise(F.greatest(F.lit(0.0), (F.least(b, hi) - F.greatest(a, lo)) / (b - a)))


def _bins(rows: DataFrame, keep: list[str]) -> DataFrame:
    """keep, a, b, w: a row for each bin. With as many weights as edges, bins are single values."""
    edges = F.col("edges")
    upper = F.when(F.size(edges) == F.size("weights"), edges).otherwise(F.slice(edges, 2, F.greatest(F.size(edges) - 1, F.lit(1))))
    lower = F.slice(edges, 1, F.size("weights"))
    return rows.select(*keep, F.explode(F.arrays_zip(lower.alias("a"), upper.alias("b"), F.col("weights").alias("w"))).alias("x")).select(*keep, "x.a", "x.b", "x.w")


def _estimated(rows: DataFrame, index: Index, region: Region, level: int) -> DataFrame:
    """(mass, moment) of each bin of the rows(lo, edges, weights) of one level that the region takes."""
    spans = [s * f**level for s, f in zip(index.spec.chunk, index.fanout)]
    share = F.lit(1.0)
    for d, runs in enumerate(region.dims):
        start = F.element_at("lo", d + 1)
        end = F.least(start + F.lit(spans[d]), F.lit(index.spec.dims[d].hi))
        inside = reduce(lambda a, b: a + b, [F.greatest(F.lit(0), F.least(end, F.lit(b)) - F.greatest(start, F.lit(a))) for a, b in runs])
        share = share * inside / (end - start)
    bins = _bins(rows.withColumn("share", share).where("share > 0"), ["share"])
    a, b = F.col("a"), F.col("b")
    parts = []
    for c in region.attr:
        mass = F.col("w") * F.col("share") * _overlap(c, a, b)
        left = a if c.lo is None else F.greatest(a, F.lit(float(c.lo)))
        right = b if c.hi is None else F.least(b, F.lit(float(c.hi)))
        parts.append(F.struct(mass.alias("mass"), (mass * (left + right) / 2).alias("moment")))
    return bins.select(F.explode(F.array(*parts)).alias("p")).select("p.mass", "p.moment").where("mass > 0")


def _totals(masses: DataFrame) -> DataFrame:
    both = masses.agg(F.coalesce(F.sum("mass"), F.lit(0.0)).alias("est_count"), F.coalesce(F.sum("moment"), F.lit(0.0)).alias("est_sum"))
    return both.withColumn("est_avg", F.when(F.col("est_count") > 0, F.col("est_sum") / F.col("est_count")))


def estimate_agg(index: Index, q: ArrayQuery, levels: int) -> DataFrame:
    """One row: estimated count, sum and mean of hits after `levels` steps, each bin's mass spread evenly over it and over
    its box. Single values count where bins are single values; in a wider bin a single value has no width, so nothing."""
    region = complete_query(q, index.spec)
    if region.empty:
        return _totals(index.spark.createDataFrame([], "mass double, moment double"))
    found = descend(index, region, levels=levels)
    parts = []
    for i, (level, kids) in enumerate(found):
        own = kids if i == len(found.steps) - 1 else kids.where("complete")
        parts.append(_estimated(index.level(level).select("z", "lo", "edges", "weights").join(own, "z"), index, region, level))
    return _totals(reduce(DataFrame.union, parts))


def estimate_from_histograms(index: Index, q: ArrayQuery) -> DataFrame:
    """One row as estimate_agg, from the chunks' histograms alone: no node and no cell is read."""
    region = complete_query(q, index.spec)
    if region.empty:
        return _totals(index.spark.createDataFrame([], "mass double, moment double"))
    return _totals(_estimated(index.leaves.select("lo", "edges", "weights"), index, region, 0))


def progressive(index: Index, q: ArrayQuery) -> DataFrame:
    """Hits tagged by the level at which they are known: complete children at once, verified cells last (level -1)."""
    region = complete_query(q, index.spec)
    cols = [*index.spec.names, index.spec.attr]
    if region.empty:
        return index.cells.select(F.lit(0).alias("level"), *cols).limit(0)
    out = []
    found = descend(index, region)
    for level, kids in found:
        tops = kids.where("complete").select(F.col("z").alias("top"))
        out.append(index.read("cells", found.cover()).join(tops, F.shiftright("z", index.bits(level)) == F.col("top"), "left_semi").select(F.lit(level).alias("level"), *cols))
    last = tagged_cells(index, region, found).where(~F.col("complete") & verified(index, region))
    return reduce(DataFrame.unionByName, [*out, last.select(F.lit(-1).alias("level"), *cols)])


def trace(index: Index, q: ArrayQuery, exact: bool = True) -> DataFrame:
    """One row for each level: children present under visited nodes, complete, partial, pruned; lookups of node bitmaps
    and of dimension masks as the descent makes them (none at nodes that their value range rejects)."""
    region = complete_query(q, index.spec)
    found = descend(index, region, exact)
    n_words = -(-int(np.prod(index.fanout)) // 64)
    attr = sum(2 * (c.lo is not None) + 2 * (c.hi is not None) + is_point(c) for c in region.attr)
    dims = sum(4 * len(runs) for runs in region.dims)
    rows = []
    parents: DataFrame | None = None
    for level, kids in found:
        seen = index.level(level + 1)
        visited = seen if parents is None else seen.join(parents, "z", "left_semi")
        present = reduce(lambda a, b: a + b, [F.bit_count(F.element_at("present", w + 1)) for w in range(n_words)])
        read = (~disjoint(region)).cast("long")
        known = visited.agg(F.count("*").alias("nodes"), F.coalesce(F.sum(present), F.lit(0)).alias("children"), F.coalesce(F.sum(read * (attr + dims)), F.lit(0)).alias("lookups"))
        real = kids.join(index.level(level).select("z"), "z", "left_semi")
        split = real.agg(F.coalesce(F.sum(F.col("complete").cast("long")), F.lit(0)).alias("complete"), F.coalesce(F.sum((~F.col("complete")).cast("long")), F.lit(0)).alias("partial"))
        rows.append(known.crossJoin(split).select(F.lit(level).alias("level"), "nodes", "children", "complete", "partial", (F.col("children") - F.col("complete") - F.col("partial")).alias("pruned"), "lookups"))
        parents = kids.where(~F.col("complete")).select("z")
    return reduce(DataFrame.unionByName, rows)


def leaf_trace(index: Index, q: ArrayQuery) -> DataFrame:
    """One row: partial leaves with hits, bitmaps read in them, cells sure, candidates to verify, false positives."""
    region = complete_query(q, index.spec)
    found = descend(index, region)
    answers = written(leaf_answers(index, region, found), "leaf-answers")
    read = answers.agg(F.count("*").alias("leaves"), F.coalesce(F.sum("reads"), F.lit(0)).alias("bitmaps"), F.coalesce(F.sum(cells_of("sure")), F.lit(0)).alias("sure"), F.coalesce(F.sum(cells_of("hit") - cells_of("sure")), F.lit(0)).alias("candidates"))
    ok = reduce(lambda a, b: a | b, [c.column(F.col(index.spec.attr)) for c in region.attr])
    looked = index.read("cells", found.cover()).join(answers, "z").where(told("hit") & ~told("sure") & ~ok)
    return read.crossJoin(looked.agg(F.count("*").alias("false_positives")))


def blocks_read(index: Index, q: ArrayQuery, exact: bool = True) -> DataFrame:
    """(block, reads): the parts of the cells that a query reads, and how often. It is at most one traversal: 1 each."""
    region = complete_query(q, index.spec)
    found = descend(index, region, exact)
    parts = index.parts_in(found.cover())
    return index.spark.createDataFrame([(p, 1) for p in parts], "block long, reads int")


def index_bytes(index: Index) -> DataFrame:
    """Bytes of bitmaps and of metadata, by level: what the paper's space measure counts."""
    rows = [index.leaves.select(F.lit(0).alias("level"), (F.coalesce(F.octet_length("present"), F.lit(0)) + F.coalesce(F.aggregate("bitmaps", F.lit(0), lambda a, x: a + F.octet_length(x)), F.lit(0))).cast("long").alias("bitmap_bytes"), (F.size("edges") * 8 + F.size("weights") * 8 + F.coalesce(F.size("list_no"), F.lit(0)) * 12 + 24 + 16 * index.spec.n).cast("long").alias("meta_bytes"))]
    for k in range(1, index.height + 1):
        node = index.level(k)
        words = lambda name: F.aggregate(name, F.lit(0), lambda a, x: a + F.size(x) * 8)
        numbers = reduce(lambda a, b: a + b, [F.size(c) for c in ("edges", "weights", "plus", "minus")])
        rows.append(node.select(F.lit(k).alias("level"), (words("started") + words("ended") + words("equal") + F.size("present") * 8).cast("long").alias("bitmap_bytes"), (numbers * 8 + 24 + 16 * index.spec.n).cast("long").alias("meta_bytes")))
    return reduce(DataFrame.union, rows).groupBy("level").agg(F.sum("bitmap_bytes").alias("bitmap_bytes"), F.sum("meta_bytes").alias("meta_bytes"))
