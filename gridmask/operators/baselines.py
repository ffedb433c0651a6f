"""The methods that the index is compared with.

Both bitmap methods are stored indexes over blocks of the row-major order, built once. Rectangle clip: one index of the
attribute; its answer becomes lines, lines are clipped by the query's boxes and merged to boxes. Dimension columns:
every dimension is an indexed column beside the attribute, and all answers are ANDed. A query reads only the bitmaps
that its ranges of bins need. Further: flat and hierarchical synopses, the chunk grid with a filter, the plain scan.
"""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import edges as E
from ..functions.codec import CODECS
from ..model import ArrayQuery, ArraySpec, Constraint, Region, collapsed, complete_query
from . import linear
from .encoding import IN_A_ROW, bin_range, bitmap_count, held_by, spread, stored
from .query import MOST_BROADCAST, bin_span, bit
from .tree import Index, grouped, ragged, runs_of, shared_folder, written

BLOCK = 32_768
#: Name of the bitmap of non-empty cells.
PRESENT = "*"
#: Number of the row of a listed block: its cells' places (PRESENT, 4 bytes each) or their bins (a column, 2 bytes each).
LISTED = -2


#: Values that a sketch of a column's distribution keeps on its lowest level: the most that it may.
SKETCH = 65_535


def global_edges(cells: DataFrame, columns: list[str], bins: int, binning: str = "equi_depth") -> dict[str, np.ndarray]:
    """Edges of each column's bins over the whole array: bins + 1 numbers a column come to the driver."""
    if binning == "equi_width":
        row = cells.agg(*[f(c).alias(f"{n}_{c}") for c in columns for n, f in (("a", F.min), ("b", F.max))]).first()
        return {c: np.unique(np.linspace(float(row[f"a_{c}"]), float(row[f"b_{c}"]), bins + 1)) for c in columns}
    if binning == "v_optimal":  # over a histogram of at most 256 equi-depth cells
        fine = global_edges(cells, columns, 256)
        out = {}
        for c, e in fine.items():
            value = F.col(c)
            at = F.size(F.filter(F.array(*[F.lit(float(x)) for x in e]), lambda x: x <= value))  # noqa: B023
            freq = {r[0] - 1: r[1] for r in cells.groupBy(at.alias("k")).count().collect()}
            out[c] = E.v_optimal(e, np.array([freq.get(k, 0) for k in range(len(e))], float), bins)[0]
        return out
    cuts = F.array(*[F.lit(k / bins) for k in range(bins + 1)])
    # a sketch takes every value: exact up to SKETCH of them, then ranks within some thousandths of a percent
    number = lambda c: F.col(c).cast("double")
    known = cells.agg(*[F.kll_sketch_agg_double(F.when(~F.isnan(number(c)), number(c)), SKETCH).alias(c) for c in columns], *[f(number(c)).alias(f"{n}_{c}") for c in columns for n, f in (("a", F.min), ("b", F.max))])
    some = lambda c: F.when(F.col(f"a_{c}").isNotNull(), F.kll_sketch_get_quantile_double(c, cuts))
    row = known.select(*[some(c).alias(c) for c in columns], *[f"{n}_{c}" for c in columns for n in "ab"]).first()
    return {c: np.unique([row[f"a_{c}"], *row[c], row[f"b_{c}"]]) for c in columns}


def block_cells(spec: ArraySpec) -> int:
    """Cells of a block: whole rows of the last dimension where they fit, so that lines end within it."""
    row = max(1, spec.dims[-1].extent)
    return BLOCK // row * row if row <= BLOCK else BLOCK


def linear_cells(cells: DataFrame, spec: ArraySpec) -> DataFrame:
    """Cells with their block and place in the array's row-major order."""
    at = linear.row_major([F.col(d.name) - F.lit(d.lo) for d in spec.dims], [d.extent for d in spec.dims])
    size = block_cells(spec)
    return cells.withColumn("at", at).withColumn("block", F.floor(F.col("at") / size)).withColumn("place", (F.col("at") % size).cast("int")).drop("at")


@dataclass
class LinearIndex:
    """A stored index of some columns over the row-major order. cells: dims, value, block, place, in order of blocks.
    bitmaps: col, k, block, bits. A block of few cells lists their places and bins instead, as the tree's leaves do."""

    spark: SparkSession
    path: str
    spec: ArraySpec
    edges: dict[str, np.ndarray]
    encoding: str
    codec: str

    @property
    def cells(self) -> DataFrame:
        names = ", ".join(f"`{d}` long" for d in self.spec.names)
        return self.spark.read.schema(f"{names}, `{self.spec.attr}` double, block long, place int").parquet(f"{self.path}/cells")

    @property
    def bitmaps(self) -> DataFrame:
        return self.spark.read.schema("k int, block long, bits binary, col string").parquet(f"{self.path}/bitmaps")

    def bins(self, col: str) -> int:
        return max(1, len(self.edges[col]) - 1)

    @property
    def blocks(self) -> int:
        return -(-math.prod(d.extent for d in self.spec.dims) // block_cells(self.spec))


def build_linear(cells: DataFrame, spec: ArraySpec, columns: list[str], bins: int = 32, encoding: str = "range", binning: str = "equi_depth", codec: str = "wah", path: str | None = None, list_below: int | None = None, raw: bool = False) -> LinearIndex:
    """Index of the columns (dimensions or the attribute): one shuffle of the cells by block, all bitmaps from there. Blocks
    of fewer cells than list_below (None: one in 64 of a block's) are listed: their bitmaps would take more. raw: several
    rows at a coordinate collapse by spec.on_collision once they are dealt; the cells are counted then."""
    spark, size = cells.sparkSession, block_cells(spec)
    path = path or f"{shared_folder(spark)}/linear-{uuid.uuid4().hex}"
    dealt = linear_cells(cells, spec).repartitionByRange("block")
    if raw:
        dealt = collapsed(dealt, ["block", "place", *spec.names], spec.on_collision, spec.attr)
    at = F.col("block") * F.lit(size) + F.col("place")
    # sorted by one number, which Spark does by its digits
    placed = dealt.select(*spec.names, spec.attr, "block", "place").sortWithinPartitions(at).persist(StorageLevel.DISK_ONLY)
    try:
        if raw:
            spec = replace(spec, n_cells=placed.count())
        edges = global_edges(placed, columns, bins, binning)
        index = LinearIndex(spark, path, spec, edges, encoding, codec)
        placed.write.mode("overwrite").parquet(f"{path}/cells")
        _write_bitmaps(index, placed.select(at.alias("at"), spec.attr), columns, list_below)
    finally:
        placed.unpersist()
    return index


def _write_bitmaps(index: LinearIndex, placed: DataFrame, columns: list[str], list_below: int | None) -> None:
    """Bitmaps from cells (place in the array, value) in order of their places, whole blocks in a partition."""
    spec, edges, encoding, codec, size = index.spec, index.edges, index.encoding, index.codec, block_cells(index.spec)
    extents = [max(1, d.extent) for d in spec.dims]
    few = size // 64 if list_below is None else list_below
    if any(len(e) > 1 << 16 for e in edges.values()):
        few = 0

    def bins_of(t: pa.Table, col: str) -> np.ndarray:
        return np.clip(np.searchsorted(edges[col], t.column(col).to_numpy(), side="right") - 1, 0, max(1, len(edges[col]) - 1) - 1)

    def columns_of(b: pa.RecordBatch) -> pa.RecordBatch:
        """block, place and the columns: coordinates follow from the place."""
        at = b.column("at").to_numpy()
        own = {d.name: x + d.lo for d, x in zip(spec.dims, np.unravel_index(at, extents))} | {spec.attr: b.column(spec.attr)}
        return pa.RecordBatch.from_arrays([pa.array(at // size), pa.array(at % size), *(pa.array(own[c]) if c != spec.attr else own[c] for c in columns)], names=["block", "place", *columns])

    def listed(t: pa.Table) -> Iterator[pa.RecordBatch]:
        """Blocks of few cells, all at once: a row for the places and one for each column."""
        block = t.column("block").to_numpy()
        first = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))
        ends = np.append(first, len(block))
        for col, kind, numbers in ((PRESENT, "<u4", t.column("place").to_numpy()), *((c, "<u2", bins_of(t, c)) for c in columns)):
            data = numbers.astype(kind)
            at = pa.py_buffer((ends * data.itemsize).astype("<i4"))
            bits = pa.BinaryArray.from_buffers(pa.binary(), len(first), [None, at, pa.py_buffer(data.tobytes())])
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(first), LISTED, np.int32)), pa.array(block[first]), bits, pa.array([col] * len(first))], names=["k", "block", "bits", "col"])

    def at_once(t: pa.Table) -> Iterator[pa.RecordBatch]:
        """Bitmaps of all blocks from their ones: a batch for the non-empty cells and one for each column."""
        block, place = (t.column(c).to_numpy() for c in ("block", "place"))
        new = np.concatenate([[True], block[1:] != block[:-1]])
        blocks, own = block[new], np.cumsum(new) - 1
        for col in (PRESENT, *columns):
            if col == PRESENT:
                m, row, at = 1, own, place
            else:
                n = max(1, len(edges[col]) - 1)
                m = bitmap_count(n, encoding)
                k, cell = spread(*held_by(bins_of(t, col), n, encoding))
                row, at = own[cell] * m + k, place[cell]
            if not m:
                continue
            ends, data = CODECS[codec].encode_ones(size, m * len(blocks), row, at)
            bits = pa.BinaryArray.from_buffers(pa.binary(), len(ends), [None, pa.py_buffer(np.concatenate([[0], ends]).astype("<i4")), pa.py_buffer(data)])
            ks = np.tile(np.arange(m) if col != PRESENT else [-1], len(blocks)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(ks), pa.array(np.repeat(blocks, m)), bits, pa.array([col] * len(ks))], names=["k", "block", "bits", "col"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        write = CODECS[codec].encode_many
        for t in grouped(map(columns_of, batches), "block"):
            block = t.column("block").to_numpy()
            _, own, cells_ = np.unique(block, return_inverse=True, return_counts=True)
            short = cells_[own] < few
            if short.any():
                yield from listed(t.filter(pa.array(short)))
            t = t.filter(pa.array(~short))
            if encoding in IN_A_ROW and t.num_rows:
                yield from at_once(t)
                continue
            for block, s, e in runs_of(t, "block") if t.num_rows else ():
                place = t.column("place").to_numpy()[s:e]
                mask = np.zeros(size, bool)
                mask[place] = True
                out = [(-1, block, write([mask])[0], PRESENT)]
                for col in columns:
                    n = max(1, len(edges[col]) - 1)
                    bin_of = np.full(size, -1, np.int64)
                    bin_of[place] = np.clip(np.searchsorted(edges[col], t.column(col).to_numpy()[s:e], side="right") - 1, 0, n - 1)
                    out += [(k, block, b, col) for k, b in enumerate(write(stored(bin_of, n, encoding)))]
                yield pa.RecordBatch.from_arrays([pa.array(c, t_) for c, t_ in zip(zip(*out), (pa.int32(), pa.int64(), pa.binary(), pa.string()))], names=["k", "block", "bits", "col"])

    rows = placed.mapInArrow(run, "k int, block long, bits binary, col string")
    rows.sortWithinPartitions("col", "k", "block").write.mode("overwrite").partitionBy("col").parquet(f"{index.path}/bitmaps")


def _asked(index: LinearIndex, wanted: dict[str, list[Constraint]]) -> tuple[dict[str, list[tuple[int, int, int, int]]], dict[str, set[int]]]:
    """For each column the spans of bins of its ranges, and which bitmaps they need: a dry run on empty masks."""
    spans: dict[str, list[tuple[int, int, int, int]]] = {}
    needed: dict[str, set[int]] = {}
    dry = np.zeros(1, bool)
    for col, ranges in wanted.items():
        bins = index.bins(col)
        spans[col] = [bin_span(c, index.edges[col], bins, False) for c in ranges]
        needed[col] = set()

        def note(k: int) -> np.ndarray:
            needed[col].add(k)  # noqa: B023
            return dry

        for first, last, first_sure, last_sure in spans[col]:
            bin_range(note, dry, bins, index.encoding, first, last)
            bin_range(note, dry, bins, index.encoding, first_sure, last_sure)
    return spans, needed


def bitmap_answers(index: LinearIndex, wanted: dict[str, list[Constraint]]) -> DataFrame:
    """(block, listed, hit, sure): words of the cells in all columns' answers, ANDed block by block, or their places if the
    block is listed; not sure where an edge bin was used. Only the bitmaps that are needed are read: two for a range under
    range or interval encoding."""
    spans, needed = _asked(index, wanted)
    size, encoding, codec = block_cells(index.spec), index.encoding, index.codec
    n_words = -(-size // 64)
    some = F.col("col") == PRESENT
    for col, ks in needed.items():
        some = some | ((F.col("col") == col) & F.col("k").isin(LISTED, *sorted(ks)))
    bins = {col: index.bins(col) for col in wanted}
    rows = index.bitmaps.where(some).select("block", "col", "k", "bits").repartition("block").sortWithinPartitions("block")

    def listed(t: pa.Table) -> pa.RecordBatch:
        """Answers of listed blocks: bins of all their cells against the spans."""
        col, bits = t.column("col").to_pylist(), t.column("bits").to_pylist()
        flat = lambda name, kind: np.frombuffer(b"".join(b for c, b in zip(col, bits) if c == name), kind)
        block = t.column("block").to_numpy()[[c == PRESENT for c in col]]
        place, n = flat(PRESENT, "<u4").astype(np.int64), np.array([len(b) // 4 for c, b in zip(col, bits) if c == PRESENT])
        hit = sure = np.ones(len(place), bool)
        for name, own in spans.items():
            k = flat(name, "<u2")
            hit = hit & reduce(np.logical_or, [(k >= a) & (k <= b) for a, b, _, _ in own])
            sure = sure & reduce(np.logical_or, [(k >= a) & (k <= b) for _, _, a, b in own])
        owner = np.repeat(np.arange(len(n)), n)
        counts = [np.bincount(owner[mask], minlength=len(n)) for mask in (hit, sure & hit)]
        some = counts[0] > 0
        return pa.RecordBatch.from_arrays([pa.array(block[some]), pa.array(np.ones(some.sum(), bool)), *(ragged(c[some], place[m], pa.int64()) for c, m in zip(counts, (hit, sure & hit)))], names=["block", "listed", "hit", "sure"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decode = CODECS[codec].decode
        for t in grouped(batches, "block"):
            short = t.column("k").to_numpy() == LISTED
            if short.any():
                yield listed(t.filter(pa.array(short)))
            t = t.filter(pa.array(~short))
            if not t.num_rows:
                continue
            blocks, words = [], ([], [])
            cols, ks, bits = (t.column(c).to_pylist() for c in ("col", "k", "bits"))
            for block, s, e in runs_of(t, "block"):
                have = {(cols[i], ks[i]): bits[i] for i in range(s, e)}
                present = decode(have[PRESENT, -1])
                hit = sure = present
                for col, own in spans.items():
                    read = lambda k, col=col: decode(have[col, k])  # noqa: B023, E731
                    hit = hit & reduce(np.logical_or, [bin_range(read, present, bins[col], encoding, a, b)[0] for a, b, _, _ in own])
                    sure = sure & reduce(np.logical_or, [bin_range(read, present, bins[col], encoding, a, b)[0] for _, _, a, b in own])
                if hit.any():
                    blocks.append(block)
                    for out, mask in zip(words, (hit, sure)):
                        padded = np.zeros(n_words * 64, bool)
                        padded[: len(mask)] = mask
                        out.append(np.packbits(padded, bitorder="little").view("<i8"))
            at = pa.array(np.arange(len(blocks) + 1, dtype=np.int32) * n_words)
            lists = [pa.ListArray.from_arrays(at, pa.array(np.concatenate(w) if w else np.zeros(0, np.int64))) for w in words]
            yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int64()), pa.array([False] * len(blocks), pa.bool_()), *lists], names=["block", "listed", "hit", "sure"])

    return rows.mapInArrow(run, "block long, listed boolean, hit array<long>, sure array<long>")


def bitmap_hits(index: LinearIndex, wanted: dict[str, list[Constraint]]) -> DataFrame:
    """The stored cells that satisfy all columns' ranges: bitmaps first, cells of edge bins by their values."""
    answers, cells = bitmap_answers(index, wanted), index.cells
    if index.blocks * block_cells(index.spec) // 4 <= MOST_BROADCAST:
        answers = F.broadcast(answers)
    else:  # what was found may be little all the same, and then tells which cells need not be read
        answers = written(answers, "bitmap-answers")
        n, first, last = answers.agg(F.sum(F.size("hit") + F.size("sure")), F.min("block"), F.max("block")).first()
        if n is None or n * 8 <= MOST_BROADCAST:
            answers = F.broadcast(answers)
            cells = cells.where(F.col("block").between(first, last) if n is not None else F.lit(False))
    holds = reduce(lambda a, b: a & b, [reduce(lambda a, b: a | b, [c.column(F.col(col)) for c in ranges]) for col, ranges in wanted.items()], F.lit(True))
    told = lambda name: F.when(F.col("listed"), F.array_contains(name, F.col("place").cast("long"))).otherwise(bit(name, "place"))
    return cells.join(answers, "block").where(told("hit") & (told("sure") | holds))


def count_bounds(index: LinearIndex, wanted: dict[str, list[Constraint]]) -> DataFrame:
    """One row: lower and upper bound of the hits from bitmaps alone, without a look at any value."""
    ones = lambda name: F.coalesce(F.sum(F.when(F.col("listed"), F.size(name)).otherwise(F.aggregate(name, F.lit(0), lambda a, w: a + F.bit_count(w)))), F.lit(0))
    return bitmap_answers(index, wanted).agg(ones("sure").alias("lower_bound"), ones("hit").alias("upper_bound"))


def wanted_columns(spec: ArraySpec, region: Region) -> dict[str, list[Constraint]]:
    """A region as ranges of columns."""
    return {d: [Constraint.between(a, b) for a, b in runs] for d, runs in zip(spec.names, region.dims)} | {spec.attr: list(region.attr)}


def dim_columns(index: LinearIndex, q: ArrayQuery) -> DataFrame:
    """Dimension columns: answers of all columns ANDed, edge bins verified."""
    spec, region = index.spec, complete_query(q, index.spec)
    cols = [*spec.names, spec.attr]
    if region.empty:
        return index.cells.select(*cols).limit(0)
    return bitmap_hits(index, wanted_columns(spec, region)).select(*cols)


# ---- rectangle clip ---------------------------------------------------------------------------------------------


def sweep(lines: np.ndarray, region_dims: tuple[tuple[tuple[int, int], ...], ...], d: int = 0) -> np.ndarray:
    """Boxes (n, dims, 2), hi exclusive, cut by the product of each dimension's runs: a sweep along dimension d finds the
    boxes that a run meets, and the rest of the dimensions are swept for those alone."""
    if d == len(region_dims) or not len(lines):
        return lines
    order = np.argsort(lines[:, d, 0], kind="stable")
    lines, out = lines[order], []
    reach = np.maximum.accumulate(lines[:, d, 1])
    for a, b in region_dims[d]:
        # boxes that begin before the run's end; those before `first` all end before it begins
        first, end = int(np.searchsorted(reach, a, side="right")), int(np.searchsorted(lines[:, d, 0], b, side="left"))
        met = lines[first:end]
        met = met[met[:, d, 1] > a].copy()
        met[:, d, 0], met[:, d, 1] = np.maximum(met[:, d, 0], a), np.minimum(met[:, d, 1], b)
        out.append(sweep(met, region_dims, d + 1))
    return np.concatenate(out)


def line_boxes(at: np.ndarray, spec: ArraySpec) -> np.ndarray:
    """Ascending row-major places -> boxes (n, dims, 2) one cell wide but in the last dimension."""
    extents = [d.extent for d in spec.dims]
    row, col = np.divmod(at, extents[-1])
    breaks = np.flatnonzero((np.diff(at) != 1) | (np.diff(row) != 0)) + 1
    first, last = np.concatenate([[0], breaks]), np.concatenate([breaks, [len(at)]]) - 1
    out = np.empty((len(first), spec.n, 2), np.int64)
    out[:, -1, 0], out[:, -1, 1] = col[first], col[last] + 1
    rest = row[first]
    for d in reversed(range(spec.n - 1)):
        rest, c = np.divmod(rest, extents[d])
        out[:, d, 0], out[:, d, 1] = c, c + 1
    return out + np.array([d.lo for d in spec.dims])[None, :, None]


def _joined(boxes: np.ndarray, d: int) -> np.ndarray:
    """Boxes that touch along d and agree elsewhere become one."""
    if len(boxes) < 2:
        return boxes
    others = [k for k in range(boxes.shape[1]) if k != d]
    keys = boxes[:, others].reshape(len(boxes), -1)
    order = np.lexsort([boxes[:, d, 0], *keys.T])
    boxes, keys = boxes[order], keys[order]
    new = np.concatenate([[True], (keys[1:] != keys[:-1]).any(axis=1) | (boxes[1:, d, 0] != boxes[:-1, d, 1])])
    first = np.flatnonzero(new)
    out = boxes[first].copy()
    out[:, d, 1] = boxes[np.append(first[1:], len(boxes)) - 1, d, 1]
    return out


def clipped_boxes(index: LinearIndex, q: ArrayQuery) -> DataFrame:
    """Boxes lo_/hi_<dim> (hi exclusive) that make up the answer.

    Some blocks at a time turn their part of the attribute's answer into lines, sweep them against the query's boxes and join
    neighbouring lines; what is left is joined across blocks. A block holds whole lines, but where a line is longer than
    a block: such a line stays in pieces.
    """
    spec, region = index.spec, complete_query(q, index.spec)
    names = [x for d in spec.names for x in (f"lo_{d}", f"hi_{d}")]
    schema = ", ".join(f"`{n}` long" for n in names)
    if region.empty:
        return index.spark.createDataFrame([], schema)
    size = block_cells(spec)
    hits = bitmap_hits(index, {spec.attr: list(region.attr)}).select("block", "place")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in grouped(batches, "block"):
            boxes = sweep(line_boxes(t.column("block").to_numpy() * size + t.column("place").to_numpy().astype(np.int64), spec), region.dims)
            if spec.n > 1:
                boxes = _joined(boxes, spec.n - 2)
            if len(boxes):
                flat = boxes.reshape(len(boxes), -1)
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(flat[:, i])) for i in range(flat.shape[1])], names=names)

    return merge_boxes(hits.repartition("block").sortWithinPartitions("block", "place").mapInArrow(run, schema), spec)


def merge_boxes(boxes: DataFrame, spec: ArraySpec) -> DataFrame:
    """Boxes that touch along a dimension and agree in all others become one; from the last dimension but one to the first."""
    for d in reversed(spec.names[:-1]):
        rest = [x for e in spec.names if e != d for x in (f"lo_{e}", f"hi_{e}")]
        w = Window.partitionBy(*rest).orderBy(f"lo_{d}")
        gap = (F.col(f"lo_{d}") != F.lag(f"hi_{d}").over(w)).cast("int")
        boxes = boxes.withColumn("gap", F.coalesce(gap, F.lit(1))).withColumn("island", F.sum("gap").over(w)).groupBy(*rest, "island").agg(F.min(f"lo_{d}").alias(f"lo_{d}"), F.max(f"hi_{d}").alias(f"hi_{d}")).drop("island")
    return boxes.select(*[x for d in spec.names for x in (f"lo_{d}", f"hi_{d}")])


def box_cells(boxes: DataFrame, spec: ArraySpec) -> DataFrame:
    for d in spec.names:
        boxes = boxes.withColumn(d, F.explode(F.sequence(F.col(f"lo_{d}"), F.col(f"hi_{d}") - 1)))
    return boxes.select(*spec.names)


def rect_clip(index: LinearIndex, q: ArrayQuery) -> DataFrame:
    """Rectangle clip: cells of the merged boxes, with their values."""
    spec = index.spec
    cols = [*spec.names, spec.attr]
    return index.cells.select(*cols).join(box_cells(clipped_boxes(index, q), spec), spec.names, "left_semi")


# ---- synopses ---------------------------------------------------------------------------------------------------


def zone_map(index: Index, q: ArrayQuery) -> DataFrame:
    """Flat synopsis: every chunk's box and value range is looked at; chunks that may hold hits are filtered."""
    region = complete_query(q, index.spec)
    if region.empty:
        return index.cells.select(*index.spec.names, index.spec.attr).limit(0)
    keep = _may_meet(index, region, 0)
    rows = index.cells.join(index.leaves.where(keep).select("z"), "z", "left_semi")
    return rows.where(q.predicate(index.spec)).select(*index.spec.names, index.spec.attr)


def _may_meet(index: Index, region: Region, level: int) -> F.Column:
    out = F.lit(True)
    for i, runs in enumerate(region.dims):
        start = F.element_at("lo", i + 1)
        span = index.spec.chunk[i] * index.fanout[i] ** level
        out = out & reduce(lambda a, b: a | b, [(start < F.lit(b)) & (start + F.lit(span) > F.lit(a)) for a, b in runs])
    return out & reduce(lambda a, b: a | b, [_range_meets(c) for c in region.attr])


def _range_meets(c: Constraint) -> F.Column:
    out = F.lit(True)
    if c.hi is not None:
        out = out & (F.col("vmin") <= float(c.hi) if c.hi_incl else F.col("vmin") < float(c.hi))
    if c.lo is not None:
        out = out & (F.col("vmax") >= float(c.lo) if c.lo_incl else F.col("vmax") > float(c.lo))
    return out


def synopsis_tree(index: Index, q: ArrayQuery) -> DataFrame:
    """Hierarchical synopsis: boxes and value ranges level by level, without bitmaps."""
    region = complete_query(q, index.spec)
    if region.empty:
        return index.cells.select(*index.spec.names, index.spec.attr).limit(0)
    alive: DataFrame | None = None
    for level in range(index.height, -1, -1):
        rows = index.level(level).where(_may_meet(index, region, level)).select("z")
        alive = rows if alive is None else rows.join(alive.withColumnRenamed("z", "top"), F.shiftright("z", index.bits(level + 1, level)) == F.col("top"), "left_semi")
    return index.cells.join(alive, "z", "left_semi").where(q.predicate(index.spec)).select(*index.spec.names, index.spec.attr)


def grid_filter(index: Index, q: ArrayQuery) -> DataFrame:
    """Dimensions choose chunks, the attribute is filtered."""
    region = complete_query(q, index.spec)
    if region.empty:
        return index.cells.select(*index.spec.names, index.spec.attr).limit(0)
    open_ = Region(region.dims, (Constraint(),))
    rows = index.cells.join(index.leaves.where(_may_meet(index, open_, 0)).select("z"), "z", "left_semi")
    return rows.where(q.predicate(index.spec)).select(*index.spec.names, index.spec.attr)


def scan(cells: DataFrame, spec: ArraySpec, q: ArrayQuery) -> DataFrame:
    return cells.where(q.predicate(spec)).select(*spec.names, spec.attr)


def bitmap_bytes(index: LinearIndex) -> DataFrame:
    """(col, bytes) of a stored index."""
    return index.bitmaps.groupBy("col").agg(F.sum(F.octet_length("bits").cast("long")).alias("bytes"))
