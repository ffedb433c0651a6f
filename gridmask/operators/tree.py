"""The chunk-tree index: leaf bitmaps over chunks, and levels of nodes over leaves.

A node's row holds words over its children. `started`: for each of the thresholds `plus`, ascending, the children whose
least value lies below it. `ended`: for each threshold in `minus`, the children whose largest value lies at or below
it. Only thresholds are kept at which the set changes, so no two stored bitmaps of a family are equal. `equal`: for each
bin the children that may hold one of its values, for queries by single values. Leaves are built in one pass over cells
dealt by chunk, levels bottom up from their children, F times fewer each time.

Stored form: a part is the subtree of one node on level `part_level`; cells, leaves and the levels below it lie in
folders by generation and part, the few nodes from there up in one folder a generation. A version file names the
generation of every part that is current. Writers add a generation for the parts that they change and then the version
file, so readers see the old index or the new one, and what did not change is not written again.
"""

from __future__ import annotations

import itertools
import json
import math
import tempfile
import uuid
from collections.abc import Callable, Iterator, Sequence
from dataclasses import asdict, dataclass, field, replace
from functools import cached_property, reduce

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import edges as E
from ..functions.codec import CODECS
from ..model import ArraySpec, collapsed
from . import linear
from .encoding import IN_A_ROW, held_by, spread, stored


@dataclass(frozen=True)
class IndexConfig:
    """bins: most bins in a leaf or node. fanout: children along each dimension (None: by the number of dimensions).
    list_below: chunks with fewer cells are listed, not bitmap-indexed (None: where a list takes less space).
    query_weights: (lo, hi, weight) of values that queries ask for, for leaf_binning "weighted".
    part_cells, most_parts: cells aimed at in a stored part, and how many parts there may be.
    node_order: how rows of cells, leaves and nodes lie in their files: "z", "row" or "hilbert".
    node_values: whether nodes over few single values keep these as bins; else bins lie between children's bounds."""

    bins: int = 16
    fanout: tuple[int, ...] | None = None
    leaf_encoding: str = "range"
    codec: str = "wah"
    leaf_binning: str = "equi_depth"
    merge: str = "equi_depth"
    list_below: int | None = None
    query_weights: tuple[tuple[float, float, float], ...] = ()
    part_cells: int = 1 << 22
    most_parts: int = 4096
    node_order: str = "z"
    node_values: bool = True

    def __post_init__(self) -> None:
        if self.bins < 2:
            raise ValueError("at least two bins")
        if self.fanout and not (2 ** len(self.fanout) <= math.prod(self.fanout) <= 4096):
            raise ValueError("fanout out of bounds")
        if self.node_order not in ("z", "row", "hilbert"):
            raise ValueError(self.node_order)


def choose_fanout(n: int, target: int | None = None) -> tuple[int, ...]:
    """Equal fanout by dimension, its product near a multiple of 64 bits: 64, 8x8, 4x4x4, 4^4, 3^5."""
    target = target or (64 if n <= 3 else 256)
    f = max(2, math.floor(target ** (1 / n) + 1e-9))
    return (f,) * n


def fit_fanout(spec: ArraySpec) -> tuple[int, ...]:
    """The usual fanout; where its Z codes would exceed 62 bits, one that follows the grid: all dimensions are at an end
    after the same number of levels, the fewest that leave a node about as many children."""
    usual = choose_fanout(spec.n)
    if tree_levels(spec, usual) * linear.step_bits(usual) <= 62:
        return usual
    for most in (512, 4096):
        for h in range(1, 63 // spec.n + 1):
            fan = tuple(next(f for f in itertools.count(max(2, int(g ** (1 / h)) - 1)) if f**h >= g) for g in spec.grid)
            if math.prod(fan) <= most and h * linear.step_bits(fan) <= 62:
                return fan
    return usual


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a temporary folder only where driver and executors are one process."""
    at = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_gridmask_folder", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        at = spark._gridmask_folder = "file://" + tempfile.mkdtemp(prefix="gridmask-")
    return at.rstrip("/")


def written(df: DataFrame, tag: str, path: str | None = None) -> DataFrame:
    """df as a Parquet table in the shared folder: lineage ends there."""
    path = path or f"{shared_folder(df.sparkSession)}/{tag}-{uuid.uuid4().hex}"
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


LEAF = "z long, lo array<long>, n_cells long, vmin double, vmax double, edges array<double>, weights array<double>, kind string, present binary, bitmaps array<binary>, list_no array<int>, list_value array<double>"
NODE = "z long, lo array<long>, n_cells long, vmin double, vmax double, edges array<double>, weights array<double>, plus array<double>, started array<array<long>>, minus array<double>, ended array<array<long>>, equal array<array<long>>, present array<long>"

# ---- versions ---------------------------------------------------------------------------------------------------


def _files(spark: SparkSession, path: str):
    """(file system, path) of the JVM's: any store that Spark reads."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at


def versions(spark: SparkSession, path: str) -> list[int]:
    fs, at = _files(spark, f"{path}/versions")
    if not fs.exists(at):
        return []
    names = [s.getPath().getName() for s in fs.listStatus(at)]
    return sorted(int(n.removesuffix(".json")) for n in names if n.endswith(".json"))


def commit(spark: SparkSession, path: str, state: dict) -> None:
    """Publish a version at once: the file appears under its name when it is whole; a version is written only once."""
    fs, at = _files(spark, f"{path}/versions/{state['version']:010d}.json")
    if fs.exists(at):
        raise RuntimeError(f"version {state['version']} of {path} exists: another writer was faster")
    _, draft = _files(spark, f"{path}/versions/.{uuid.uuid4().hex}")
    out = fs.create(draft)
    out.write(bytearray(json.dumps(state).encode()))
    out.close()
    if not fs.rename(draft, at):
        raise RuntimeError(f"version {state['version']} of {path} could not be published")


def read_state(spark: SparkSession, path: str, version: int | None = None) -> dict:
    found = versions(spark, path)
    if not found or version is not None and version not in found:
        raise FileNotFoundError(f"{path}: version {version or 'any'}")
    text = spark.read.text(f"{path}/versions/{version or found[-1]:010d}.json", wholetext=True).first()[0]
    return json.loads(text)


# ---- the index --------------------------------------------------------------------------------------------------


def merge_ranges(ranges: list[tuple[int, int]], most: int | None = None) -> list[tuple[int, int]]:
    """Half-open ranges in order, touching ones joined; with `most`, the smallest gaps are closed until so few are left."""
    out: list[list[int]] = []
    for a, b in sorted(ranges):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    if most is not None and len(out) > most:
        gaps = sorted(range(1, len(out)), key=lambda i: out[i][0] - out[i - 1][1])
        closed = set(gaps[: len(out) - most])
        joined = [out[0]]
        for i in range(1, len(out)):
            if i in closed:
                joined[-1][1] = out[i][1]
            else:
                joined.append(out[i])
        out = joined
    return [(a, b) for a, b in out]


def in_ranges(name: str, ranges: list[tuple[int, int]]) -> Column:
    """The column lies in one of the half-open ranges; as one SQL text, which is faster to plan than many columns."""
    tests = [f"`{name}` = {a}L" if b == a + 1 else f"(`{name}` >= {a}L AND `{name}` < {b}L)" for a, b in ranges]
    return F.expr(" OR ".join(tests)) if tests else F.lit(False)


@dataclass
class Index:
    """An index at one version. Tables: cells (dims, value, z, cell_no), leaves (level 0), level(k) of nodes; the last
    level is the root alone. read(k, ranges) gives a table's rows in ranges of leaf codes, from the parts they touch."""

    spark: SparkSession
    path: str
    spec: ArraySpec
    config: IndexConfig
    state: dict
    #: Up to so many nodes of a frontier are held by the driver and walked in memory; 0: none, all by DataFrames.
    dense_rows: int = 4096
    _dense: dict = field(default_factory=dict)
    _tables: dict = field(default_factory=dict)

    @property
    def fanout(self) -> tuple[int, ...]:
        return self.config.fanout

    @property
    def height(self) -> int:
        return self.state["height"]

    @property
    def part_level(self) -> int:
        return self.state["part_level"]

    @property
    def parts(self) -> dict[int, int]:
        """Part -> generation that holds it."""
        return {int(k): g for k, g in self.state["parts"].items()}

    @cached_property
    def layout(self) -> linear.Layout:
        """Bits of each dimension in a Z code, by level."""
        return linear.code_layout(self.spec.grid, self.fanout, self.height)

    @cached_property
    def _below(self) -> list[int]:
        return linear.bits_below(self.layout)

    def bits(self, k: int, under: int = 0) -> int:
        """Bits by which the code of a node of level `under` is longer than that of its ancestor of level k."""
        return self._below[k] - self._below[under]

    @property
    def shift(self) -> int:
        """Bits of a leaf's Z code below its part's number."""
        return self.bits(self.part_level)

    def _schema(self, name: str) -> str:
        if name == "cells":
            return ", ".join(f"`{d}` long" for d in self.spec.names) + f", `{self.spec.attr}` double, z long, cell_no int"
        return LEAF if name == "level=0" else NODE

    def _load(self, name: str, parts: Sequence[int] | None) -> DataFrame:
        spark, base = self.spark, f"{self.path}/{name}"
        k = None if name == "cells" else int(name.split("=")[1])
        if k is not None and k >= self.part_level and k > 0:
            return spark.read.schema(self._schema(name)).parquet(f"{base}/gen={self.state['top']}")
        schema = f"{self._schema(name)}, gen int, part long"
        chosen = self.parts if parts is None else {p: self.parts[p] for p in parts}
        if not chosen:
            return spark.createDataFrame([], schema)
        whole = {g for g, ps in self.state["whole"].items() if parts is None and all(self.parts.get(p) == int(g) for p in ps)}
        folders = [f"{base}/gen={g}" for g in sorted(whole)] + [f"{base}/gen={g}/part={p}" for p, g in sorted(chosen.items()) if str(g) not in whole]
        return spark.read.schema(schema).option("basePath", base).parquet(*folders)

    def read(self, name: str, ranges: list[tuple[int, int]] | None = None) -> DataFrame:
        """Rows of a table; with ranges of leaf codes, only those of the parts and codes in the ranges are read."""
        cols = [c.split()[0].strip("`") for c in self._schema(name).replace(", ", "\n").split("\n")]
        if ranges is None:
            if name not in self._tables:
                self._tables[name] = self._load(name, None)
            return self._tables[name].select(*cols)
        k = 0 if name == "cells" else int(name.split("=")[1])
        parts = None
        if name == "cells" or k < self.part_level or k == 0:
            parts = self.parts_in(ranges)
            if len(self.parts) <= 256:  # files are listed once for all queries
                if name not in self._tables:
                    self._tables[name] = self._load(name, None)
                rows = self._tables[name].where(F.expr(f"part IN ({', '.join(f'{p}L' for p in parts)})") if parts else F.lit(False))
            else:  # only the chosen folders are listed
                rows = self._load(name, parts)
        else:
            rows = self.read(name)
        below = self.bits(k)
        few = merge_ranges([(a >> below, ((b - 1) >> below) + 1) for a, b in ranges], 16)
        if parts is not None and sum(b - a for a, b in few) * 2 > len(parts) << max(0, self.shift - below):
            return rows.select(*cols)  # most of the parts is wanted: a filter on codes would only cost
        return rows.where(in_ranges("z", few)).select(*cols)

    def parts_in(self, ranges: list[tuple[int, int]]) -> list[int]:
        """Parts that hold any of the leaf codes, exactly."""
        starts = [a for a, _ in ranges]
        return [p for p in sorted(self.parts) if (i := int(np.searchsorted(starts, (p + 1) << self.shift)) - 1) >= 0 and ranges[i][1] > p << self.shift]

    @property
    def cells(self) -> DataFrame:
        return self.read("cells")

    @property
    def leaves(self) -> DataFrame:
        return self.read("level=0")

    def level(self, k: int) -> DataFrame:
        return self.read(f"level={k}")

    def span(self, z: int, k: int) -> tuple[int, int]:
        """Leaf codes under a node of level k."""
        below = self.bits(k)
        return z << below, (z + 1) << below

    def node_rows(self, k: int, zs: list[int]) -> dict[int, dict]:
        """Nodes of level k by code: from memory if the whole level is small, else only the asked ones are read."""
        if self._bound(k) <= self.dense_rows:
            if k not in self._dense:
                self._dense[k] = _in_memory(self.level(k))
            return self._dense[k]
        asked = F.expr(f"z IN ({', '.join(f'{z}L' for z in zs)})") if zs else F.lit(False)
        return _in_memory(self.read(f"level={k}", merge_ranges([self.span(z, k) for z in zs])).where(asked))

    def _bound(self, k: int) -> int:
        """Nodes that level k can have."""
        return math.prod(-(-g // f**k) for g, f in zip(self.spec.grid, self.fanout))

    def child_span(self, k: int) -> list[int]:
        """Coordinates that a child of a level-k node covers along each dimension."""
        return [s * f ** (k - 1) for s, f in zip(self.spec.chunk, self.fanout)]


def _in_memory(rows: DataFrame) -> dict[int, dict]:
    """Node rows by code, bitmaps as whole numbers."""
    joined = lambda words: sum((w & ((1 << 64) - 1)) << (64 * i) for i, w in enumerate(words))
    out = {}
    for r in rows.select("z", "lo", "vmin", "vmax", "edges", "weights", "plus", "started", "minus", "ended", "equal", "present").collect():
        out[r.z] = {"lo": r.lo, "vmin": r.vmin, "vmax": r.vmax, "edges": r.edges, "by_value": len(r.edges) == len(r.weights), "plus": r.plus, "minus": r.minus, "started": [joined(w) for w in r.started], "ended": [joined(w) for w in r.ended], "equal": [joined(w) for w in r.equal], "present": joined(r.present)}
    return out


def tree_levels(spec: ArraySpec, fanout: tuple[int, ...]) -> int:
    h = 1
    while any(f**h < g for f, g in zip(fanout, spec.grid)):
        h += 1
    return h


def tree_height(spec: ArraySpec, fanout: tuple[int, ...]) -> int:
    h = tree_levels(spec, fanout)
    if linear.bits_below(linear.code_layout(spec.grid, fanout, h))[-1] > linear.MOST_BITS:
        raise ValueError("Z codes exceed 62 bits: larger chunks or fanout are needed")
    return h


def choose_part_level(spec: ArraySpec, cfg: IndexConfig, levels: int) -> int:
    """The lowest level that has no more nodes than parts are wanted."""
    wanted = min(cfg.most_parts, max(1, (spec.n_cells or math.prod(d.extent for d in spec.dims)) // cfg.part_cells))
    for k in range(levels + 1):
        if math.prod(-(-g // f**k) for g, f in zip(spec.grid, cfg.fanout)) <= wanted:
            return k
    return levels


def to_words(mask: np.ndarray, n: int) -> list[int]:
    """Slots (bool, n) -> signed 64-bit words."""
    padded = np.zeros(-(-n // 64) * 64, bool)
    padded[:n] = mask
    return np.packbits(padded, bitorder="little").view("<i8").tolist()


def grouped(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """Tables of whole groups from batches sorted by key; a group is a chunk or a node, so it is bounded."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        k = b.column(key).to_numpy(zero_copy_only=False)
        before = np.flatnonzero(k != k[-1])
        cut = int(before[-1]) + 1 if len(before) else 0
        if cut or held and held[-1].column(key)[0].as_py() != k[0]:
            yield pa.Table.from_batches([*held, b.slice(0, cut)])
            held = [b.slice(cut)]
        else:
            held.append(b)
    if held:
        yield pa.Table.from_batches(held)


def runs_of(table: pa.Table, key: str) -> Iterator[tuple[int, int, int]]:
    k = table.column(key).to_numpy()
    bounds = [0, *(np.flatnonzero(k[1:] != k[:-1]) + 1).tolist(), len(k)]
    for s, e in zip(bounds, bounds[1:]):
        yield int(k[s]), s, e


BINNING: dict[str, Callable] = {
    "equi_depth": E.equi_depth,
    "equi_width": E.equi_width,
    "v_optimal": lambda v, b: (lambda e: (e, E.bin_counts(v, e)))(E.v_optimal(*np.unique(v, return_counts=True), b)[0]),
}


def leaf_row(z: int, lo: list[int], numbers: np.ndarray, values: np.ndarray, spec: ArraySpec, cfg: IndexConfig) -> tuple:
    """One chunk's leaf: few distinct values get a bin each, else bins by the configured rule."""
    order = np.sort(values)
    few = np.unique(order)
    if len(few) <= cfg.bins:
        edges, weights = few, E.bin_counts(order, np.append(few, np.inf))
        edges = few
    elif cfg.leaf_binning == "weighted":
        asked = np.ones(len(order))
        for a, b, w in cfg.query_weights:
            asked[(order >= a) & (order < b)] += w
        edges, weights = E.weighted_equi_depth(order, asked, cfg.bins)
    else:
        edges, weights = BINNING[cfg.leaf_binning](order, cfg.bins)
    n, cells = len(values), spec.chunk_cells
    head = (z, lo, n, float(order[0]), float(order[-1]), edges.tolist(), weights.tolist())
    if n < list_limit(spec, cfg):
        return (*head, "list", None, None, numbers.tolist(), values.tolist())
    bins = leaf_bins(edges, len(few) <= cfg.bins)
    bin_of = np.full(cells, -1, np.int64)
    bin_of[numbers] = np.clip(np.searchsorted(edges, values, side="right") - 1, 0, bins - 1)
    kind = "values" if len(few) <= cfg.bins else "bins"
    present, *bitmaps = CODECS[cfg.codec].encode_many([bin_of >= 0, *stored(bin_of, bins, cfg.leaf_encoding)])
    return (*head, kind, present, bitmaps, None, None)


LEAF_SCHEMA = pa.schema([("z", pa.int64()), ("lo", pa.list_(pa.int64())), ("n_cells", pa.int64()), ("vmin", pa.float64()), ("vmax", pa.float64()), ("edges", pa.list_(pa.float64())), ("weights", pa.list_(pa.float64())), ("kind", pa.string()), ("present", pa.binary()), ("bitmaps", pa.list_(pa.binary())), ("list_no", pa.list_(pa.int32())), ("list_value", pa.list_(pa.float64()))])


def ragged(sizes: np.ndarray, flat: np.ndarray, kind: pa.DataType) -> pa.ListArray:
    """Lists of so many numbers each."""
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.array(flat, kind))


def leaf_rows(z: np.ndarray, numbers: np.ndarray, values: np.ndarray, spec: ArraySpec, cfg: IndexConfig, levels: int) -> Iterator[pa.RecordBatch]:
    """Leaves of whole chunks, whose cells follow one another: those listed or under a plain encoding all at once, as leaf_row makes
    them one by one."""
    first = np.flatnonzero(np.concatenate([[True], z[1:] != z[:-1]]))
    n = np.diff(first, append=len(z))
    order = np.lexsort([values, z])
    v = values[order]
    new = np.concatenate([[True], v[1:] != v[:-1]])
    new[first] = True
    few = np.add.reduceat(new, first)
    single = few <= cfg.bins
    at = linear.decode_z(z[first], cfg.fanout, levels, linear.code_layout(spec.grid, cfg.fanout, levels))
    lo = np.stack([d.lo + a * c for d, a, c in zip(spec.dims, at, spec.chunk)], axis=1)
    short = n < list_limit(spec, cfg)
    easy = (short | (cfg.leaf_encoding in IN_A_ROW)) & (single | (cfg.leaf_binning == "equi_depth"))
    if easy.any():
        # places of the edges in v: all first places of a value, or those of the order statistics and the last place
        places, owner = [np.flatnonzero(new & np.repeat(single & easy, n))], []
        wide = np.flatnonzero(easy & ~single)
        ranks = np.concatenate([(np.arange(cfg.bins)[None] * n[wide, None]) // cfg.bins, n[wide, None] - 1], axis=1)
        places.append((ranks + first[wide, None]).ravel())
        begin = np.maximum.accumulate(np.where(new, np.arange(len(v)), 0))
        kept = np.unique(begin[np.concatenate(places)])
        owner = np.searchsorted(first, kept, side="right") - 1
        last = np.append(owner[1:] != owner[:-1], True)
        end = np.where(last, (first + n)[owner], np.append(kept[1:], 0))
        # a wide leaf's last edge closes the bin before it
        closes = last & ~single[owner]
        before = np.append(closes[1:], False)
        end = np.where(before, (first + n)[owner], end)
        groups, cells = np.flatnonzero(easy), np.repeat(easy, n)
        count = np.bincount(owner, minlength=len(first))[groups]
        # bins of the cells in bitmaps: edges are first places of values, so the last at or before a cell's place is its bin's
        drawn = np.flatnonzero(easy & ~short)
        inked = np.flatnonzero(np.repeat(easy & ~short, n))
        per, at_edge = np.bincount(owner, minlength=len(first)), np.searchsorted(owner, np.arange(len(first)))
        bins = np.maximum(1, per - ~single)
        leaf = np.repeat(np.arange(len(first)), n)[inked]
        bin_of = np.minimum(np.searchsorted(kept, inked, side="right") - 1 - at_edge[leaf], bins[leaf] - 1)
        m = {"equality": bins, "range": bins - 1, "interval": (bins + 1) // 2}.get(cfg.leaf_encoding, bins * 0) + 1
        begin_row = np.zeros(len(first), np.int64)
        begin_row[drawn] = np.cumsum(m[drawn]) - m[drawn]
        k, cell = spread(*held_by(bin_of, bins[leaf], cfg.leaf_encoding)) if len(inked) else (inked, inked)
        number = numbers[order][inked]
        ends, data = CODECS[cfg.codec].encode_ones(spec.chunk_cells, int(m[drawn].sum()), np.concatenate([begin_row[leaf], begin_row[leaf[cell]] + 1 + k]), np.concatenate([number, number[cell]]))
        maps = pa.BinaryArray.from_buffers(pa.binary(), len(ends), [None, pa.py_buffer(np.concatenate([[0], ends]).astype("<i4")), pa.py_buffer(data)])
        listed, row = short[groups], begin_row[groups]
        present = maps.take(pa.array(row, mask=listed))
        rest = np.ones(len(maps), bool)
        rest[begin_row[drawn]] = False
        held = np.where(listed, 0, m[groups] - 1)
        drawings = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(held)]).astype(np.int32), mask=np.append(listed, False)), maps.filter(pa.array(rest)))
        shown = np.repeat(short, n)
        kind = pa.array(np.where(listed, "list", np.where(single[groups], "values", "bins")))

        def lists(flat: np.ndarray, type_: pa.DataType) -> pa.ListArray:
            at = np.concatenate([[0], np.cumsum(np.where(listed, n[groups], 0))]).astype(np.int32)
            return pa.ListArray.from_arrays(pa.array(at, mask=np.append(~listed, False)), pa.array(flat[cells & shown], type_))

        columns = [pa.array(z[first][groups]), ragged(np.full(len(groups), spec.n), lo[groups].ravel(), pa.int64()), pa.array(n[groups], pa.int64()), pa.array(v[first][groups]), pa.array(v[first + n - 1][groups]), ragged(count, v[kept], pa.float64()), ragged(count - ~single[groups], (end - kept)[~closes].astype(float), pa.float64()), kind, present, drawings, lists(numbers, pa.int32()), lists(values, pa.float64())]
        yield pa.RecordBatch.from_arrays(columns, schema=LEAF_SCHEMA)
    rows = [leaf_row(int(z[first[g]]), lo[g].tolist(), numbers[first[g] : first[g] + n[g]], values[first[g] : first[g] + n[g]], spec, cfg) for g in np.flatnonzero(~easy)]
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), LEAF_SCHEMA)], schema=LEAF_SCHEMA)


def list_limit(spec: ArraySpec, cfg: IndexConfig) -> int:
    """Chunks with fewer cells are listed."""
    return cfg.list_below if cfg.list_below is not None else (cfg.bins + 1) * spec.chunk_cells // 8 // 12


def leaf_bins(edges: np.ndarray, by_value: bool) -> int:
    """A leaf of single values has a bin for each edge; one of ranges has one bin fewer than edges."""
    return len(edges) if by_value else max(1, len(edges) - 1)


def build_leaves(cells: DataFrame, spec: ArraySpec, cfg: IndexConfig, levels: int, dealt: bool = False) -> DataFrame:
    """Leaves of cells(z, cell_no, value). dealt: each chunk's cells already follow one another within one partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in grouped(batches, "z"):
            if t.num_rows:
                yield from leaf_rows(*(t.column(c).to_numpy() for c in ("z", "cell_no", "v")), spec, cfg, levels)

    rows = cells.select("z", "cell_no", F.col(spec.attr).alias("v"))
    if not dealt:
        rows = rows.repartition("z").sortWithinPartitions("z", "cell_no")
    return rows.mapInArrow(run, LEAF)


@dataclass
class Bins:
    """The bins of a node's children, one after another: edges e and weights w, and for each child how many of both. A child
    with as many weights as edges holds just those values; its masses are points."""

    e: np.ndarray
    w: np.ndarray
    n_edges: np.ndarray
    n_weights: np.ndarray

    def __post_init__(self) -> None:
        n = len(self.n_edges)
        self.by_value = self.n_edges == self.n_weights
        self.e_child, self.w_child = np.repeat(np.arange(n), self.n_edges), np.repeat(np.arange(n), self.n_weights)
        self.point = self.by_value[self.e_child]
        self.mass = self.by_value[self.w_child]

    def ends(self) -> tuple[np.ndarray, np.ndarray]:
        """Left and right end of every weight."""
        first, place = np.cumsum(self.n_edges) - self.n_edges, np.arange(len(self.w)) - np.repeat(np.cumsum(self.n_weights) - self.n_weights, self.n_weights)
        left = first[self.w_child] + place
        return self.e[left], self.e[left + np.where(self.n_edges > self.n_weights, 1, 0)[self.w_child]]

    def spread(self, edges: np.ndarray) -> np.ndarray:
        """Mass in each interval between edges, as edges.spread_mass."""
        if len(edges) < 2:
            return np.array([self.w.sum()])
        at = np.clip(np.searchsorted(edges, self.e[self.point], side="right") - 1, 0, len(edges) - 2)
        out = np.bincount(at, self.w[self.mass], len(edges) - 1).astype(float)
        if self.by_value.all():
            return out
        # children's bins in rows of one width: edges, and the mass up to each
        own = np.flatnonzero(~self.by_value)
        n_edges, wide = self.n_edges[own], ~self.by_value
        row = np.repeat(np.arange(len(own)), n_edges)
        place = np.arange(len(row)) - np.repeat(np.cumsum(n_edges) - n_edges, n_edges)
        e, w = np.full((2, len(own), n_edges.max()), [[[np.inf]], [[0.0]]])
        e[row, place] = self.e[wide[self.e_child]]
        inner = place > 0
        w[row[inner], place[inner]] = self.w[wide[self.w_child]]
        upto = np.cumsum(w, axis=1)
        # for each child how many of its edges lie at or below each of the given ones
        at = np.searchsorted(edges, e[row, place])
        count = np.bincount(row * (len(edges) + 1) + at, minlength=len(own) * (len(edges) + 1)).reshape(len(own), -1)[:, :-1].cumsum(axis=1)
        j = np.clip(count - 1, 0, n_edges[:, None] - 2)
        left, base = np.take_along_axis(e, j, 1), np.take_along_axis(upto, j, 1)
        slope = (np.take_along_axis(upto, j + 1, 1) - base) / (np.take_along_axis(e, j + 1, 1) - left)
        mass = np.where(count == 0, 0.0, np.where(count >= n_edges[:, None], upto[:, -1:], slope * (edges - left) + base))
        return np.add.reduce(np.concatenate([out[None], np.diff(mass, axis=1)]), axis=0)

    def holding(self, edges: np.ndarray, by_value: bool) -> np.ndarray:
        """(bins, children): children that may hold a value of the bin: one of their bins with any mass, both ends taken as
        inside, meets it. Mass is spread evenly over bins, so every value lies in some bin that has mass, ends included."""
        bins = len(edges) if by_value else max(1, len(edges) - 1)
        left, right = self.ends()
        some = self.w > 0
        begin = np.clip(np.searchsorted(edges, left[some], side="right") - 1, 0, bins - 1)
        end = np.clip(np.searchsorted(edges, right[some], side="right") - 1, 0, bins - 1)
        steps = np.zeros((bins + 1, len(self.n_edges)), np.int64)
        np.add.at(steps, (begin, self.w_child[some]), 1)
        np.add.at(steps, (end + 1, self.w_child[some]), -1)
        return np.cumsum(steps, axis=0)[:bins] > 0


def node_row(z: int, lo: list[int], children: dict, fanout: tuple[int, ...], cfg: IndexConfig, edges: np.ndarray | None = None) -> tuple:
    """A node from its children's slots, least and largest values, cells, edges and weights; given edges are kept."""
    e, w = children["edges"], children["weights"]
    flat = Bins(np.concatenate([np.asarray(x, float) for x in e]), np.concatenate([np.asarray(x, float) for x in w]), np.array([len(x) for x in e]), np.array([len(x) for x in w]))
    return node_of(z, lo, *(np.array(children[k]) for k in ("slot", "vmin", "vmax", "n_cells")), flat, math.prod(fanout), cfg, edges)


def node_of(z: int, lo: list[int], slots: np.ndarray, lows: np.ndarray, highs: np.ndarray, n_cells: np.ndarray, bins: Bins, n: int, cfg: IndexConfig, edges: np.ndarray | None = None) -> tuple:
    """A node of n slots from its children's bins.

    A child with as many weights as edges holds just those values. Where all children do and the values are few, so
    does the node, and its bins are the values.
    """
    every = np.unique(np.concatenate([lows, highs]))
    by_value = cfg.node_values and bool(bins.by_value.all())
    if by_value:
        values = np.unique(bins.e)
        by_value = len(values) <= cfg.bins
    if by_value:
        kept = values
        weights = np.bincount(np.searchsorted(kept, bins.e), bins.w, len(kept)).astype(float)
    else:
        if edges is not None:  # bins stay as they are; only the outer bounds follow the data
            inner = edges[(edges > every[0]) & (edges < every[-1])]
            kept = np.unique(np.concatenate([every[:1], inner, every[-1:]]))
        elif len(every) <= cfg.bins + 1:
            kept = every
        elif cfg.merge == "by_sign":
            kept = E.reduce_by_sign(lows, highs, every, bins.spread(every), cfg.bins)
        else:
            kept = E.REDUCE[cfg.merge](every, bins.spread(every), cfg.bins)
        weights = bins.spread(kept)  # one value: a point

    def words(chosen: np.ndarray) -> list[list[int]]:
        """Rows of children -> rows of words."""
        mask = np.zeros((len(chosen), -(-n // 64) * 64), bool)
        mask[:, slots] = chosen
        return np.packbits(mask, axis=1, bitorder="little").view("<i8").tolist()

    # of thresholds with equal sets the largest stands for "started", the smallest for "ended"; no set is stored that
    # is all or none
    begun, over = lows[None] < kept[1:, None], highs[None] <= kept[:, None]
    started, ended = begun.sum(axis=1), over.sum(axis=1)
    plus = np.flatnonzero((started < len(lows)) & np.append(started[1:] != started[:-1], True)[: len(started)])
    minus = np.flatnonzero((ended > 0) & np.concatenate([[True], ended[1:] != ended[:-1]]))
    head = (z, lo, int(n_cells.sum()), float(every[0]), float(every[-1]), kept.tolist(), weights.tolist())
    return (*head, kept[plus + 1].tolist(), words(begun[plus]), kept[minus].tolist(), words(over[minus]), words(bins.holding(kept, by_value)), words(np.ones((1, len(slots)), bool))[0])


def distinct(group: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Values of each group once, ascending: their groups, themselves, and for each given one its number among them."""
    order = np.lexsort([values, group])
    g, v = group[order], values[order]
    new = np.concatenate([[True], (g[1:] != g[:-1]) | (v[1:] != v[:-1])])[: len(v)]
    number = np.empty(len(v), np.int64)
    number[order] = np.cumsum(new) - 1
    return g[new], v[new], number


def nested(sizes: np.ndarray, rows: np.ndarray) -> pa.ListArray:
    """Lists of so many rows of words each."""
    inner = ragged(np.full(len(rows), rows.shape[1]), rows.view(np.int64).ravel(), pa.int64())
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), inner)


@dataclass
class Children:
    """Children of whole nodes, which follow one another: their node's number, slot, bounds, cells, and how many edges and
    weights each has of those in e and w."""

    node: np.ndarray
    slot: np.ndarray
    low: np.ndarray
    high: np.ndarray
    n_cells: np.ndarray
    n_edges: np.ndarray
    n_weights: np.ndarray
    e: np.ndarray
    w: np.ndarray

    def of(self, chosen: np.ndarray) -> Children:
        """The children of the chosen nodes (bool), whose nodes are numbered anew."""
        mine = chosen[self.node]
        some = [getattr(self, k)[mine] for k in ("slot", "low", "high", "n_cells", "n_edges", "n_weights")]
        return Children((np.cumsum(chosen) - 1)[self.node[mine]], *some, self.e[np.repeat(mine, self.n_edges)], self.w[np.repeat(mine, self.n_weights)])


def bounds_of(c: Children, n: int) -> np.ndarray:
    """How many bounds the children of each of n nodes have."""
    return np.bincount(distinct(np.concatenate([c.node, c.node]), np.concatenate([c.low, c.high]))[0], minlength=n)


def plain_nodes(c: Children, n: int, cfg: IndexConfig) -> np.ndarray:
    """Which of n nodes need no bins reduced: their children hold single values, and these or the bounds are few."""
    points = np.ones(n, bool)
    points[c.node[c.n_edges != c.n_weights]] = False
    bounds = bounds_of(c, n)
    values = np.bincount(distinct(np.repeat(c.node, c.n_edges), c.e)[0], minlength=n)
    return points & (((values <= cfg.bins) & cfg.node_values) | ((bounds > 1) & (bounds <= cfg.bins + 1)))


def plain_node_rows(z: np.ndarray, lo: np.ndarray, c: Children, n_slots: int, cfg: IndexConfig, schema: pa.Schema) -> pa.RecordBatch:
    """Rows of plain nodes, all at once, as node_of makes them one by one."""
    n = len(z)
    point = np.repeat(np.arange(len(c.node)), c.n_edges)
    owner, values, number = distinct(c.node[point], c.e)
    by_value = (np.bincount(owner, minlength=n) <= cfg.bins) & cfg.node_values
    bound_of, bounds, _ = distinct(np.concatenate([c.node, c.node]), np.concatenate([c.low, c.high]))
    # edges of all nodes, one node after another
    of = np.concatenate([owner[by_value[owner]], bound_of[~by_value[bound_of]]])
    edges = np.concatenate([values[by_value[owner]], bounds[~by_value[bound_of]]])
    order = np.argsort(of, kind="stable")
    of, edges = of[order], edges[order]
    last = np.cumsum(np.bincount(of, minlength=n)) - 1
    # the bin of each point: the last edge at or below it, of bounds not the last of all
    both = np.lexsort([np.repeat([0, 1], [len(edges), len(point)]), np.concatenate([edges, c.e]), np.concatenate([of, c.node[point]])])
    at = np.empty(len(both), np.int64)
    at[both] = np.cumsum(both < len(edges)) - 1
    at = np.minimum(at[len(edges) :], (last - ~by_value)[c.node[point]])
    weights = np.bincount(at, c.w, len(edges)).astype(float)
    held = np.unique(at[c.w > 0] * len(c.node) + point[c.w > 0])
    return rows_of_edges(z, lo, c, n_slots, schema, of, edges, by_value, weights, held)


def rows_of_edges(z: np.ndarray, lo: np.ndarray, c: Children, n_slots: int, schema: pa.Schema, of: np.ndarray, edges: np.ndarray, by_value: np.ndarray, weights: np.ndarray, held: np.ndarray) -> pa.RecordBatch:
    """Rows of nodes whose edges are known, one node's after another's: of their nodes, by_value for each node. weights: the
    mass of the bin that begins at each edge. held: ascending numbers edge * children + child of children in that bin."""
    n = len(z)
    n_edges = np.bincount(of, minlength=n)
    first, last = np.cumsum(n_edges) - n_edges, np.cumsum(n_edges) - 1
    is_bin = np.ones(len(edges), bool)
    is_bin[last[~by_value]] = False

    n_words, word, bit = -(-n_slots // 64), c.slot // 64, np.uint64(1) << (c.slot % 64).astype(np.uint64)

    def words(row: np.ndarray, child: np.ndarray, rows: int) -> np.ndarray:
        """Bits of children in rows, each at most once in a row; rows ascend."""
        out = np.zeros((rows, n_words), np.uint64)
        if len(row):
            begin = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]]))
            for k in range(n_words):
                out[row[begin], k] = np.add.reduceat(np.where(word[child] == k, bit[child], np.uint64(0)), begin)
        return out

    # each edge beside each child of its node
    kids = np.bincount(c.node, minlength=n)
    width = kids[of]
    edge = np.repeat(np.arange(len(edges)), width)
    child = np.arange(len(edge)) - np.repeat(np.cumsum(width) - width, width) + (np.cumsum(kids) - kids)[of][edge]
    begun, over = c.low[child] < edges[edge], c.high[child] <= edges[edge]
    started, ended = np.bincount(edge[begun], minlength=len(edges)), np.bincount(edge[over], minlength=len(edges))
    inner, final = np.ones(len(edges), bool), np.zeros(len(edges), bool)
    inner[first], final[last] = False, True
    plus = inner & (started < width) & (final | np.append(started[1:] != started[:-1], True))
    minus = (ended > 0) & (~inner | np.concatenate([[True], ended[1:] != ended[:-1]]))
    plus_rows, minus_rows = (words(edge[some], child[some], len(edges))[kept] for some, kept in ((begun, plus), (over, minus)))
    equal_rows = words(held // len(c.node), held % len(c.node), len(edges))[is_bin]
    count = lambda kept: np.bincount(of[kept], minlength=n)
    begin = np.cumsum(kids) - kids
    low, high = np.minimum.reduceat(c.low, begin), np.maximum.reduceat(c.high, begin)
    columns = [z, ragged(np.full(n, lo.shape[1]), lo.ravel(), pa.int64()), np.add.reduceat(c.n_cells, begin), low, high, ragged(n_edges, edges, pa.float64()), ragged(count(is_bin), weights[is_bin], pa.float64())]
    columns += [ragged(count(plus), edges[plus], pa.float64()), nested(count(plus), plus_rows), ragged(count(minus), edges[minus], pa.float64()), nested(count(minus), minus_rows), nested(count(is_bin), equal_rows)]
    columns.append(ragged(np.full(n, n_words), words(c.node, np.arange(len(c.node)), n).view(np.int64).ravel(), pa.int64()))
    return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x) for x in columns], schema=schema)


#: Numbers that wide_node_rows holds at once for one purpose.
MOST_AT_ONCE = 1 << 22


def filled(sizes: np.ndarray, flat: np.ndarray, rest: float) -> np.ndarray:
    """Rows of so many numbers each, filled up with the rest."""
    out = np.full((len(sizes), int(sizes.max())), rest)
    out[np.arange(out.shape[1])[None] < sizes[:, None]] = flat
    return out


def spread_many(c: Children, edges: np.ndarray, n_edges: np.ndarray) -> np.ndarray:
    """Bins.spread for the children of many nodes, with a row of edges for each node, filled up with infinity."""
    wide = edges.shape[1]
    point, mass_of = c.n_edges == c.n_weights, np.repeat(np.arange(len(c.node)), c.n_weights)
    e_of = np.repeat(np.arange(len(c.node)), c.n_edges)
    # how many edges of its node lie below each child's edge, and at or below it
    def places(x: np.ndarray, of: np.ndarray, or_at: bool) -> np.ndarray:
        own = np.repeat(np.arange(len(edges)), n_edges)
        flat = edges[np.arange(wide)[None] < n_edges[:, None]]
        tie = [0, 1] if or_at else [1, 0]
        both = np.lexsort([np.repeat(tie, [len(flat), len(x)]), np.concatenate([flat, x]), np.concatenate([own, of])])
        at = np.empty(len(both), np.int64)
        at[both] = np.cumsum(both < len(flat))
        return at[len(flat) :] - (np.cumsum(n_edges) - n_edges)[of]

    single = point[e_of]
    node = c.node[e_of[single]]
    at = np.clip(places(c.e[single], node, True) - 1, 0, n_edges[node] - 2)
    out = np.bincount(node * (wide - 1) + at, c.w[point[mass_of]], len(edges) * (wide - 1)).astype(float).reshape(len(edges), -1)
    own = np.flatnonzero(~point)
    if not len(own):
        return out
    node, own_edges = c.node[own], c.n_edges[own]
    x = c.e[~single]
    row = np.repeat(np.arange(len(own)), own_edges)
    e = filled(own_edges, x, np.inf)
    upto = np.cumsum(np.concatenate([np.zeros((len(own), 1)), filled(own_edges - 1, c.w[~point[mass_of]], 0.0)], axis=1), axis=1)
    count = np.bincount(row * (wide + 1) + places(x, node[row], False), minlength=len(own) * (wide + 1)).reshape(len(own), -1)[:, :-1].cumsum(axis=1)
    j = np.clip(count - 1, 0, own_edges[:, None] - 2)
    left, base = np.take_along_axis(e, j, 1), np.take_along_axis(upto, j, 1)
    with np.errstate(invalid="ignore"):  # beyond a node's last edge
        slope = (np.take_along_axis(upto, j + 1, 1) - base) / (np.take_along_axis(e, j + 1, 1) - left)
        mass = np.where(count == 0, 0.0, np.where(count >= own_edges[:, None], upto[:, -1:], slope * (edges[node] - left) + base))
    # summed child by child, as for one node
    kids = np.bincount(node, minlength=len(edges))
    parts = np.zeros((len(edges), 1 + kids.max(), wide - 1))
    parts[:, 0] = out
    parts[node, 1 + np.arange(len(node)) - (np.cumsum(kids) - kids)[node]] = np.diff(mass, axis=1)
    return np.add.reduce(parts, axis=1)


def wide_node_rows(z: np.ndarray, lo: np.ndarray, c: Children, n_slots: int, cfg: IndexConfig, schema: pa.Schema) -> pa.RecordBatch:
    """Rows of nodes of several bounds, bins reduced by "equi_depth" where they are many: as node_of makes them one by one."""
    n = len(z)
    bound_of, bounds, _ = distinct(np.concatenate([c.node, c.node]), np.concatenate([c.low, c.high]))
    n_edges = np.bincount(bound_of, minlength=n)
    edges = filled(n_edges, bounds, np.inf)
    many = n_edges > cfg.bins + 1
    if many.any():
        sizes, some = n_edges[many], edges[many]
        kept = E.reduce_equi_depth_many(some, sizes, spread_many(c.of(many), some, sizes), cfg.bins)
        n_edges = np.where(many, cfg.bins + 1, n_edges)
        edges = edges[:, : n_edges.max()].copy()
        edges[many, : cfg.bins + 1] = np.take_along_axis(some, kept, 1)
        edges[np.arange(edges.shape[1])[None] >= n_edges[:, None]] = np.inf
    mass = spread_many(c, edges, n_edges)
    real = np.arange(edges.shape[1])[None] < n_edges[:, None]
    weights = np.concatenate([mass, np.zeros((n, 1))], axis=1)[real]
    # bins of the node that each child's bins meet, both ends taken as inside
    e_at, w_child = np.cumsum(c.n_edges) - c.n_edges, np.repeat(np.arange(len(c.node)), c.n_weights)
    left = e_at[w_child] + np.arange(len(c.w)) - np.repeat(np.cumsum(c.n_weights) - c.n_weights, c.n_weights)
    some = c.w > 0
    child, left = w_child[some], left[some]
    right = left + (c.n_edges > c.n_weights)[child]
    node, width = c.node[child], edges.shape[1]
    begin, end = (np.clip((edges[node] <= c.e[at][:, None]).sum(axis=1) - 1, 0, n_edges[node] - 2) for at in (left, right))
    steps = np.bincount(child * (width + 1) + begin, minlength=len(c.node) * (width + 1)) - np.bincount(child * (width + 1) + end + 1, minlength=len(c.node) * (width + 1))
    kid, own = np.nonzero(np.cumsum(steps.reshape(len(c.node), -1), axis=1) > 0)
    held = np.sort(((np.cumsum(n_edges) - n_edges)[c.node[kid]] + own) * len(c.node) + kid)
    return rows_of_edges(z, lo, c, n_slots, schema, np.repeat(np.arange(n), n_edges), edges[real], np.zeros(n, bool), weights, held)


def build_level(children: DataFrame, spec: ArraySpec, cfg: IndexConfig, level: int, levels: int, old: DataFrame | None = None, together: int = 0) -> DataFrame:
    """Nodes of `level` from the level below. old(z, edges): nodes whose bins are kept. together: nodes under one node so
    many levels up are made in one task."""
    fan = cfg.fanout
    layout = linear.code_layout(spec.grid, fan, levels)
    step = sum(layout[level - 1])
    n_slots = math.prod(fan)
    slots = np.zeros(1 << step, np.int64)
    digits, first_slots = np.unique(linear.slot_z(fan, layout[level - 1]), return_index=True)
    slots[digits] = first_slots
    rows = children.select(F.shiftright("z", step).alias("parent"), F.col("z").bitwiseAND(F.lit((1 << step) - 1)).alias("digit"), "n_cells", "vmin", "vmax", F.size("edges").alias("n_edges"), F.concat("edges", "weights").alias("both"))  # one list: each takes its time on the way to Python
    if old is not None:
        rows = rows.join(old.select(F.col("z").alias("parent"), F.col("edges").alias("kept")), "parent", "left")
    dims, chunk = spec.dims, spec.chunk

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = pa.list_(pa.int64())
        numbers, masks = pa.list_(pa.float64()), pa.list_(words)
        schema = pa.schema([("z", pa.int64()), ("lo", words), ("n_cells", pa.int64()), ("vmin", pa.float64()), ("vmax", pa.float64()), ("edges", numbers), ("weights", numbers), ("plus", numbers), ("started", masks), ("minus", numbers), ("ended", masks), ("equal", masks), ("present", words)])
        for t in grouped(batches, "parent"):
            if not t.num_rows:
                continue
            rows = []
            parent, low, high, cells, slot = (t.column(k).to_numpy() for k in ("parent", "vmin", "vmax", "n_cells", "digit"))
            both = t.column("both").combine_chunks()
            both = both.chunk(0) if isinstance(both, pa.ChunkedArray) else both
            n_edges, n_both = t.column("n_edges").to_numpy().astype(np.int64), np.diff(both.offsets.to_numpy())
            # flatten() starts at the first list's beginning, whatever the offsets are
            flat, place = both.flatten().to_numpy(), np.arange(n_both.sum()) - np.repeat(np.cumsum(n_both) - n_both, n_both)
            is_edge = place < np.repeat(n_edges, n_both)
            e_flat, w_flat = flat[is_edge], flat[~is_edge]
            e_at, w_at = (np.concatenate([[0], np.cumsum(n)]) for n in (n_edges, n_both - n_edges))
            kept_of = t.column("kept") if "kept" in t.column_names else None
            first = np.flatnonzero(np.concatenate([[True], parent[1:] != parent[:-1]]))
            node = np.repeat(np.arange(len(first)), np.diff(first, append=len(parent)))
            every = Children(node, slots[slot], low, high, cells, np.diff(e_at), np.diff(w_at), e_flat, w_flat)
            at = linear.decode_z(parent[first], fan, levels - level, layout[level:])
            lo = np.stack([d.lo + a * k * f**level for d, a, k, f in zip(dims, at, chunk, fan)], axis=1)
            fresh = np.ones(len(first), bool) if kept_of is None else kept_of.is_null().to_numpy()[first]
            plain = plain_nodes(every, len(first), cfg) & fresh
            if plain.any():
                yield plain_node_rows(parent[first][plain], lo[plain], every.of(plain), n_slots, cfg, schema)
            wide = ~plain & fresh & (bounds_of(every, len(first)) > 1) & (cfg.merge == "equi_depth")
            kids = np.diff(first, append=len(parent))
            # some nodes at a time: each takes a number for every child and bound
            for some in np.array_split(np.flatnonzero(wide), 1 + int(2 * wide.sum() * kids.max() ** 2) // MOST_AT_ONCE):
                if len(some):
                    chosen = np.zeros(len(first), bool)
                    chosen[some] = True
                    yield wide_node_rows(parent[first][some], lo[some], every.of(chosen), n_slots, cfg, schema)
            for g in np.flatnonzero(~plain & ~wide):
                s, e = int(first[g]), int(first[g + 1]) if g + 1 < len(first) else len(parent)
                bins = Bins(e_flat[e_at[s] : e_at[e]], w_flat[w_at[s] : w_at[e]], every.n_edges[s:e], every.n_weights[s:e])
                kept = None if kept_of is None else kept_of[s].as_py()
                rows.append(node_of(int(parent[s]), lo[g].tolist(), every.slot[s:e], low[s:e], high[s:e], cells[s:e], bins, n_slots, cfg, None if kept is None else np.array(kept)))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    dealt = rows.repartition(F.shiftright("parent", sum(map(sum, layout[level : level + together]))) if together else F.col("parent")).sortWithinPartitions("parent", "digit")
    return dealt.mapInArrow(run, NODE)


def place_cells(cells: DataFrame, spec: ArraySpec, fanout: tuple[int, ...], levels: int) -> DataFrame:
    """Cells with the Z code of their chunk and their number in it."""
    z = linear.z_code(linear.chunk_coords(spec), fanout, levels, linear.code_layout(spec.grid, fanout, levels))
    return cells.select(*spec.names, spec.attr, z.alias("z"), linear.row_major(linear.local_coords(spec), spec.chunk).cast("int").alias("cell_no"))


def chunk_order(spec: ArraySpec, fanout: tuple[int, ...], levels: int) -> list[Column]:
    """Order of cells by chunk and number in it: one number where both fit, which Spark sorts by its digits."""
    bits = (spec.chunk_cells - 1).bit_length()
    if linear.bits_below(linear.code_layout(spec.grid, fanout, levels))[-1] + bits > 63:
        return [F.col("z"), F.col("cell_no")]
    return [F.shiftleft("z", bits).bitwiseOR(F.col("cell_no").cast("long"))]


def file_order(index: Index, level: int) -> list[Column | str]:
    """What rows of a part are sorted by. Codes are prefixes of the part's whatever the order within a part."""
    order = index.config.node_order
    if order == "z":
        return ["z"]
    bits = linear.own_bits(index.fanout)
    total = max(bits) * max(1, index.height - level)
    above = index.layout[level:]
    if all(f == 1 << max(bits) for f in index.fanout) and all(own == bits for own in above):
        at = linear.deinterleave(F.col("z"), index.spec.n, total)
    else:  # digits of the fanout, each in bits of its own
        groups = [linear.deinterleave(F.shiftright("z", below).bitwiseAND(F.lit((1 << sum(own)) - 1)), index.spec.n, own) for below, own in zip(linear.bits_below(above), above or [bits])]
        at = [reduce(lambda x, y: x + y, [g[d] * F.lit(f**k) for k, g in enumerate(groups)]) for d, f in enumerate(index.fanout)]
    return at if order == "row" else [linear.hilbert_code(at, total)]


def write_parts(index: Index, name: str, rows: DataFrame, gen: int) -> None:
    """Rows of a table into the generation's folders, one for each part, in file order."""
    k = 0 if name == "cells" else int(name.split("=")[1])
    folder = f"{index.path}/{name}/gen={gen}"
    order = [*file_order(index, k), *(["cell_no"] if name == "cells" else [])]
    if name != "cells" and k > 0 and k >= index.part_level:
        rows.coalesce(1).sortWithinPartitions(*order).write.mode("overwrite").parquet(folder)
        return
    if "part" not in rows.columns:
        rows = in_parts(index, name, rows)
    rows.write.mode("overwrite").partitionBy("part").parquet(folder)


def in_parts(index: Index, name: str, rows: DataFrame, dealt: bool = False) -> DataFrame:
    """Rows of a table below the parts' level with their part, dealt (if they are not) and sorted as they are stored."""
    k = 0 if name == "cells" else int(name.split("=")[1])
    placed = rows.withColumn("part", F.shiftright("z", index.bits(index.part_level, k)))
    if name == "cells" and not dealt:
        placed = placed.repartitionByRange("z")
    return placed.sortWithinPartitions("part", *file_order(index, k), *(["cell_no"] if name == "cells" else []))


def build_index(cells: DataFrame, spec: ArraySpec, cfg: IndexConfig | None = None, path: str | None = None, previous: dict | None = None, raw: bool = False) -> Index:
    """Index of one attribute. Cells are read once to be placed; their leaves are made from what that left.

    previous: the state of an index at path that this one replaces, as its next version. raw: several rows at a coordinate
    collapse by spec.on_collision once they are dealt, which takes no shuffle of its own; the cells are counted then.
    """
    spark = cells.sparkSession
    cfg = cfg or IndexConfig()
    if cfg.fanout is None:
        cfg = replace(cfg, fanout=fit_fanout(spec))
    levels = tree_height(spec, cfg.fanout)
    path = (path or f"{shared_folder(spark)}/index-{uuid.uuid4().hex}").rstrip("/")
    taken = versions(spark, path)
    gen = (previous["gen"] if previous else read_state(spark, path)["gen"] if taken else 0) + 1
    dealt = place_cells(cells, spec, cfg.fanout, levels).repartitionByRange("z")
    if raw:
        dealt = collapsed(dealt, ["z", "cell_no", *spec.names], spec.on_collision, spec.attr)
    columns = [*spec.names, spec.attr, "z", "cell_no"]
    # dealt and sorted once, for the cells' files and for the leaves
    placed = dealt.select(*columns).sortWithinPartitions(*chunk_order(spec, cfg.fanout, levels)).persist(StorageLevel.DISK_ONLY)
    try:
        if raw:
            spec = replace(spec, n_cells=placed.count())
        state = {"version": taken[-1] + 1 if taken else 1, "gen": gen, "top": gen, "height": levels, "part_level": choose_part_level(spec, cfg, levels), "parts": {}, "whole": {}, "batches": (previous or {}).get("batches", {})}
        draft = Index(spark, path, spec, cfg, state)
        write_parts(draft, "cells", in_parts(draft, "cells", placed, dealt=True), gen)
        write_parts(draft, "level=0", build_leaves(placed, spec, cfg, levels, dealt=True), gen)
    finally:
        placed.unpersist()
    leaves = spark.read.schema(f"{LEAF}, part long").parquet(f"{path}/level=0/gen={gen}")
    # as many rows as parts, which are bounded
    state["parts"] = {str(r[0]): gen for r in leaves.select("part").distinct().collect()}
    state["whole"] = {str(gen): sorted(int(p) for p in state["parts"])}
    # a part's nodes from one task are one file; few parts would leave tasks without work, and are few files anyway
    many = len(state["parts"]) >= 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    for k in range(1, levels + 1):
        together = max(0, draft.part_level - k) if many else 0
        write_parts(draft, f"level={k}", build_level(Index(spark, path, spec, cfg, state).level(k - 1), spec, cfg, k, levels, together=together), gen)
    return publish(draft, state)


def publish(index: Index, state: dict) -> Index:
    """Write the version file; the index at that version."""
    state = state | {"spec": index.spec.to_json(), "config": asdict(index.config)}
    commit(index.spark, index.path, state)
    return Index(index.spark, index.path, index.spec, index.config, state, index.dense_rows)


def read_index(spark: SparkSession, path: str, version: int | None = None) -> Index:
    path = path.rstrip("/")
    state = read_state(spark, path, version)
    listed = {"fanout": tuple(state["config"]["fanout"]), "query_weights": tuple(map(tuple, state["config"].get("query_weights", ())))}
    return Index(spark, path, ArraySpec.from_json(state["spec"]), IndexConfig(**(state["config"] | listed)), state)


def vacuum(index: Index) -> int:
    """Delete folders and version files that this version does not need; readers of older ones must be gone."""
    spark, gone = index.spark, 0
    needed = set(index.parts.values()) | {index.state["top"]}
    for name in ["cells", *(f"level={k}" for k in range(index.height + 1))]:
        fs, at = _files(spark, f"{index.path}/{name}")
        for s in fs.listStatus(at) if fs.exists(at) else []:
            gen = int(s.getPath().getName().split("=")[1])
            stale = [s.getPath()] if gen not in needed else [p.getPath() for p in fs.listStatus(s.getPath()) if p.getPath().getName().startswith("part=") and index.parts.get(int(p.getPath().getName().split("=")[1])) != gen]
            for p in stale:
                gone += bool(fs.delete(p, True))
    for v in versions(spark, index.path):
        if v < index.state["version"]:
            fs, at = _files(spark, f"{index.path}/versions/{v:010d}.json")
            gone += bool(fs.delete(at, False))
    return gone
