"""Append and modification: new cells rebuild their chunks' leaves and the nodes above them, in the parts they fall in.

The touched parts are written as a new generation, the few nodes above the parts with them; every other part stays as
it is on disk. A version file then makes the change visible at once. Nodes on the path keep their bins (outer bounds
follow the data), or get new ones with rebalance. When the shape outgrows the root, the tree gains levels: Z codes only
gain leading zero digits, so rows below stay as they are. Cells below the origin would move every chunk, and a dimension
that gains digits in codes that leave out zero ones would move every code: then the whole index is built again as the
next version.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import ArraySpec, Dim
from . import linear
from .tree import Index, build_index, build_leaves, build_level, merge_ranges, place_cells, publish, tree_height, write_parts, written


def grown_spec(spec: ArraySpec, new_cells: DataFrame) -> ArraySpec:
    """Domains extended by the new cells."""
    ends = [f(d).alias(f"{p}{i}") for i, d in enumerate(spec.names) for p, f in (("l", F.min), ("h", F.max))]
    row = new_cells.agg(F.count("*").alias("n"), *ends).first()
    dims = []
    for i, d in enumerate(spec.dims):
        lo, hi = row[f"l{i}"], row[f"h{i}"]
        dims.append(d if lo is None else Dim(d.name, min(d.lo, lo), max(d.hi, hi + 1)))
    return replace(spec, dims=tuple(dims), n_cells=spec.n_cells + row["n"])


def _combine(old: DataFrame, new: DataFrame, keys: list[str], attr: str, on_collision: str) -> DataFrame:
    """Cells of both: with "replace" the new value wins, else both collapse by max, min or sum."""
    both = old.select(*keys, attr, F.lit(0).alias("age")).unionByName(new.select(*keys, attr, F.lit(1).alias("age")))
    value = {"max": F.max(attr), "min": F.min(attr), "sum": F.sum(attr), "replace": F.max_by(attr, "age")}[on_collision]
    return both.groupBy(*keys).agg(value.alias(attr))


def append(index: Index, new_cells: DataFrame, rebalance: bool = False, on_collision: str = "max", batch: tuple[str, int] | None = None) -> Index:
    """The index with new_cells(dims, value) in it, as its next version.

    batch: (stream, number). A number that this or an earlier version has taken changes nothing; the number is
    published together with the cells, so a batch that comes again after a restart is not taken twice.
    """
    if batch is not None and batch[1] <= index.state["batches"].get(batch[0], -1):
        return index
    spec, cfg, spark = grown_spec(index.spec, new_cells), index.config, index.spark
    batches = index.state["batches"] | ({batch[0]: batch[1]} if batch else {})
    if any(a.lo < b.lo for a, b in zip(spec.dims, index.spec.dims)):
        cells = written(_combine(index.cells, new_cells, spec.names, spec.attr, on_collision), "all-cells")
        return build_index(cells, spec, cfg, index.path, index.state | {"batches": batches})
    levels, gen = max(tree_height(spec, cfg.fanout), index.height), index.state["gen"] + 1
    if linear.code_layout(spec.grid, cfg.fanout, levels)[: index.height] != index.layout:  # codes would be others
        cells = written(_combine(index.cells, new_cells, spec.names, spec.attr, on_collision), "all-cells")
        return build_index(cells, spec, cfg, index.path, index.state | {"batches": batches})
    draft = Index(spark, index.path, spec, cfg, index.state | {"gen": gen, "top": gen, "height": levels}, index.dense_rows)
    fresh = written(place_cells(new_cells, spec, cfg.fanout, levels), "new-cells")
    touched = written(fresh.select("z").distinct(), "touched")
    # parts are bounded, so are the touched ones
    parts = sorted(r[0] for r in touched.select(F.shiftright("z", draft.shift)).distinct().collect())
    if not parts:
        return publish(index, index.state | {"version": index.state["version"] + 1, "batches": batches}) if batch else index
    state = draft.state | {"version": index.state["version"] + 1, "batches": batches, "parts": {**index.state["parts"], **{str(p): gen for p in parts}}, "whole": index.state["whole"] | {str(gen): parts}}
    after = Index(spark, index.path, spec, cfg, state, index.dense_rows)
    held = [p for p in parts if p in index.parts]

    def old(name: str) -> DataFrame:
        """Rows of the touched parts as they were."""
        rows = index._load(name, held)
        return rows.drop("gen", "part")

    keys = [*spec.names, "z", "cell_no"]
    was = old("cells")
    changed = written(_combine(was.join(touched, "z", "left_semi"), fresh, keys, spec.attr, on_collision), "changed-cells")
    names = [*spec.names, spec.attr, "z", "cell_no"]
    write_parts(after, "cells", was.join(touched, "z", "left_anti").select(*names).unionByName(changed.select(*names)), gen)
    write_parts(after, "level=0", old("level=0").join(touched, "z", "left_anti").unionByName(build_leaves(changed, spec, cfg, levels)), gen)
    path = touched
    for k in range(1, levels + 1):
        path = path.select(F.shiftright("z", after.bits(k, k - 1)).alias("z")).distinct()
        if k > index.height:  # new levels are built whole: they have few nodes
            write_parts(after, f"level={k}", build_level(after.level(k - 1), spec, cfg, k, levels), gen)
            continue
        partly = k < index.part_level
        had = old(f"level={k}") if partly else index.level(k)
        if k <= index.part_level:  # children of the path lie in the touched parts
            near = after._load(f"level={k - 1}", parts).drop("gen", "part")
        else:  # or, above the parts, under as few nodes as there are touched parts
            tops = {p >> after.bits(k, index.part_level) for p in parts}
            near = after.read(f"level={k - 1}", merge_ranges([after.span(n, k) for n in tops]))
        kids = near.join(path.withColumnRenamed("z", "up"), F.shiftright("z", after.bits(k, k - 1)) == F.col("up"), "left_semi")
        kept = None if rebalance else had.join(path, "z", "left_semi").select("z", "edges")
        write_parts(after, f"level={k}", had.join(path, "z", "left_anti").unionByName(build_level(kids, spec, cfg, k, levels, kept)), gen)
    return publish(after, state)


def modify(index: Index, new_cells: DataFrame, rebalance: bool = False) -> Index:
    """Cells that exist get new values: their chunks and the nodes above are rebuilt."""
    return append(index, new_cells, rebalance, on_collision="replace")
