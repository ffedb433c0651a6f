"""spark.read.format("gridmask").option("index", path): cells of a written index, pruned by pushed filters.

Comparisons and IN on dimensions and the attribute choose leaves by their boxes and value ranges while planning: from the
root down, so only nodes and leaves under nodes that meet the filters are read. What is left is filtered again by Spark.
Files are read with pyarrow, so the path must be on a store that pyarrow's file systems reach from every executor.
"""

from __future__ import annotations

import json
from collections.abc import Iterator, Sequence

import pyarrow as pa
import pyarrow.dataset as ds
from pyarrow import fs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from ..model import ArraySpec
from ..operators.linear import bits_below, code_layout, slot_z


def _opened(path: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path.removeprefix("file:"))


class LeafGroup(InputPartition):
    def __init__(self, zs: list[int]) -> None:
        self.zs = zs


class IndexReader(DataSourceReader):
    def __init__(self, path: str, group: int) -> None:
        self.path, self.group = path.rstrip("/"), group
        store, at = _opened(self.path)
        found = [i.path for i in store.get_file_info(fs.FileSelector(f"{at}/versions")) if i.base_name.endswith(".json")]
        with store.open_input_stream(max(found)) as f:
            self.state = json.loads(f.read())
        self.spec, self.config = json.loads(self.state["spec"]), self.state["config"]
        self.layout = code_layout(ArraySpec.from_json(self.state["spec"]).grid, self.config["fanout"], self.state["height"])
        self.below = bits_below(self.layout)
        self.bounds: dict[str, list[float]] = {}

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Ranges narrow what is read; every filter goes back, so that Spark has the last word."""
        for f in filters:
            name = f.attribute[0] if len(getattr(f, "attribute", ())) == 1 else None
            lo, hi = float("-inf"), float("inf")
            if isinstance(f, EqualTo):
                lo = hi = f.value
            elif isinstance(f, GreaterThan | GreaterThanOrEqual):
                lo = f.value
            elif isinstance(f, LessThan | LessThanOrEqual):
                hi = f.value
            elif isinstance(f, In) and f.value:
                lo, hi = min(f.value), max(f.value)
            else:
                name = None
            if name is not None:
                old = self.bounds.get(name, [float("-inf"), float("inf")])
                self.bounds[name] = [max(old[0], lo), min(old[1], hi)]
            yield f

    def rows(self, name: str, level: int, zs: list[int], columns: list[str]) -> pa.Table | None:
        """Rows of a table with these codes, from the folders that hold them."""
        store, at = _opened(self.path)
        k = self.state["part_level"]
        if name != "cells" and level >= k and level > 0:
            folders = [f"{at}/{name}/gen={self.state['top']}"]
        else:
            parts = sorted({z >> (self.below[k] - self.below[level]) for z in zs})
            folders = [f"{at}/{name}/gen={self.state['parts'][str(p)]}/part={p}" for p in parts if str(p) in self.state["parts"]]
        files = [i.path for f in folders for i in store.get_file_info(fs.FileSelector(f)) if i.base_name.endswith(".parquet")]
        if not files:
            return None
        z = ds.field("z")
        return ds.dataset(files, filesystem=store, format="parquet").to_table(columns=columns, filter=(z >= min(zs)) & (z <= max(zs)) & z.isin(zs))

    def leaves(self) -> list[int]:
        """Z codes of leaves whose box and value range meet the pushed bounds, found from the root down."""
        names = [d["name"] for d in self.spec["dims"]]
        box = [self.bounds.get(n, [float("-inf"), float("inf")]) for n in names]
        low, high = self.bounds.get(self.spec["attr"], [float("-inf"), float("inf")])
        height, fanout, found = self.state["height"], self.config["fanout"], [0]
        for level in range(height, -1, -1):
            t = self.rows(f"level={level}", level, found, ["z", "lo", "vmin", "vmax", *(["present"] if level else [])]) if found else None
            found = []
            if t is None:
                break
            for z, lo, a, b, *present in zip(*(c.to_pylist() for c in t.columns)):
                span = [s * f**level for s, f in zip(self.spec["chunk"], fanout)]
                if a <= high and b >= low and all(x <= e and x + n > s for x, n, (s, e) in zip(lo, span, box)):
                    if level == 0:
                        found.append(z)
                    else:
                        bits = sum((w & ((1 << 64) - 1)) << (64 * i) for i, w in enumerate(present[0]))
                        own = self.layout[level - 1]
                        found += [z << sum(own) | digit for i, digit in enumerate(slot_z(fanout, own)) if bits >> i & 1]
        return sorted(found)

    def partitions(self) -> Sequence[InputPartition]:
        z = self.leaves()
        return [LeafGroup(z[i : i + self.group]) for i in range(0, len(z), self.group)] or [LeafGroup([])]

    def read(self, partition: LeafGroup) -> Iterator[pa.RecordBatch]:
        if not partition.zs:
            return
        names = [d["name"] for d in self.spec["dims"]] + [self.spec["attr"]]
        t = self.rows("cells", 0, partition.zs, names)
        if t is not None:
            yield from t.to_batches()


class IndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "gridmask"

    def schema(self) -> StructType:
        r = self.reader(StructType())
        return StructType([*(StructField(d["name"], LongType()) for d in r.spec["dims"]), StructField(r.spec["attr"], DoubleType())])

    def reader(self, schema: StructType) -> IndexReader:
        return IndexReader(self.options["index"], int(self.options.get("leaves", "64")))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(IndexSource)
