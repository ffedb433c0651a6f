"""Operators around arrays that users combine with queries: box overlap, runs, bitmaps as aggregates, hinted joins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import BinaryType, IntegerType, StructField, StructType

from ..functions.codec import pack, unpack
from ..model import ArraySpec
from .linear import int_div


def overlap_boxes(boxes: DataFrame, cells: DataFrame, spec: ArraySpec) -> DataFrame:
    """box, chunk coordinates and number of cells for each pair of a box and a non-empty chunk that share a coordinate.

    boxes(box, lo_<dim>, hi_<dim> for every dim; upper bounds exclusive). A box names the chunks it meets, so the join is
    an equi-join on chunk coordinates; boxes are clipped to the array first, so they name no more chunks than it has.
    """
    keys = [f"c{i}" for i in range(spec.n)]
    met = boxes
    for i, (d, side) in enumerate(zip(spec.dims, spec.chunk)):
        lo, hi = F.greatest(F.col(f"lo_{d.name}"), F.lit(d.lo)), F.least(F.col(f"hi_{d.name}"), F.lit(d.hi))
        met = met.where(lo < hi).withColumn(f"c{i}", F.explode(F.sequence(int_div(lo - d.lo, side), int_div(hi - 1 - d.lo, side))))
    placed = cells.select(*(int_div(F.col(d.name) - d.lo, s).alias(k) for k, d, s in zip(keys, spec.dims, spec.chunk)))
    return met.select("box", *keys).join(placed.groupBy(*keys).agg(F.count("*").alias("n_cells")), keys)


def value_runs(cells: DataFrame, spec: ArraySpec, holds: Column) -> DataFrame:
    """Runs along the last dimension in which every cell is there and `holds`: leading dims, first, last, length."""
    *lead, along = spec.names
    w = Window.partitionBy(*lead).orderBy(along)
    fresh = cells.where(holds).withColumn("fresh", F.when(F.col(along) == F.lag(along).over(w) + 1, 0).otherwise(1))
    told = fresh.withColumn("run", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return told.groupBy(*lead, "run").agg(F.min(along).alias("first"), F.max(along).alias("last"), F.count("*").alias("length")).drop("run")


def pivot_blocks(cells: DataFrame, spec: ArraySpec, along: str, prefix: str) -> DataFrame:
    """One row for each line along a dimension and each block of a chunk's side on it: other dims, <along>_from, a column a slot.

    The blocks cover the whole domain, so a line of any length is told in rows of bounded width.
    """
    i = spec.names.index(along)
    d, side = spec.dims[i], spec.chunk[i]
    lead = [n for n in spec.names if n != along]
    slot = F.pmod(F.col(along) - d.lo, F.lit(side)).cast("int")
    placed = cells.select(*lead, (F.col(along) - slot).alias(f"{along}_from"), slot.alias("slot"), spec.attr)
    wide = placed.groupBy(*lead, f"{along}_from").pivot("slot", list(range(side))).agg(F.max(spec.attr))
    return wide.select(*lead, f"{along}_from", *(F.col(str(k)).alias(f"{prefix}{k}") for k in range(side)))


def as_of_all(cells: DataFrame, spec: ArraySpec, along: str) -> DataFrame:
    """The latest value at every coordinate of the fitted domain, from a line's first cell on: other dims, along, latest.

    A cell answers for the places up to the next cell of its line, so no grid is made and joined.
    """
    d = spec.dims[spec.names.index(along)]
    lead = [n for n in spec.names if n != along]
    following = F.lead(along, 1, d.hi).over(Window.partitionBy(*lead).orderBy(along))
    held = cells.select(*lead, F.col(along).alias("since"), (following - 1).alias("until"), F.col(spec.attr).alias("latest"))
    return held.select(*lead, F.explode(F.sequence("since", "until")).alias(along), "latest")


@pandas_udf(BinaryType())
def bitmap_of(numbers: pd.Series) -> bytes:
    """Aggregate of cell numbers into a raw bitmap, for groups of one chunk's size."""
    n = numbers.to_numpy(np.int64)
    bits = np.zeros(int(n.max()) + 1 if len(n) else 0, bool)
    bits[n] = True
    return pack(bits)


@udtf(returnType=StructType([StructField("cell_no", IntegerType())]))
class BitmapPositions:
    """Table function: the positions of a raw bitmap's ones."""

    def eval(self, payload: bytes) -> Iterator[tuple[int]]:
        if payload:
            for i in np.flatnonzero(unpack(payload, 8 * len(payload))).tolist():
                yield (i,)


def hinted_join(left: DataFrame, right: DataFrame, on: list[str], how: str) -> DataFrame:
    """Equi-join of two large sides by a stated physical method: 'shuffle_hash' or 'merge'. Neither side is broadcast."""
    if how not in ("shuffle_hash", "merge"):
        raise ValueError(f"unknown join method {how!r}")
    return left.join(right.hint(how), on)
