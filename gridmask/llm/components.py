"""Connected components of an edge table, without bringing nodes or links to the driver.

Each round replaces the links of every node by links to its smallest neighbour, first towards larger neighbours,
then towards smaller ones (large-star and small-star). The links end as a star around the smallest node of each
component, after about log(n) rounds. The driver only compares two sums from round to round.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import materialize


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, root) for the links a[i] - b[i], root the smallest node of its component; roots themselves left out."""
    if not len(a):
        return a, b
    nodes, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = ends[: len(a)], ends[len(a) :]
    root = np.arange(len(nodes))
    while True:
        rx, ry = root[x], root[y]
        open_ = rx != ry
        if not open_.any():
            break
        x, y, rx, ry = x[open_], y[open_], rx[open_], ry[open_]
        np.minimum.at(root, np.maximum(rx, ry), np.minimum(rx, ry))
        while True:
            up = root[root]
            if (up == root).all():
                break
            root = up
    below = np.flatnonzero(root != np.arange(len(nodes)))
    return nodes[below], nodes[root[below]]


def _local_forests(links: DataFrame, batch: int = 1_000_000) -> DataFrame:
    """As few links as a task can tell to be enough; memory is bounded by the batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        n = 0

        def flush() -> pa.RecordBatch:
            a, b = forest(*(np.concatenate(x) for x in zip(*held)))
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["u", "v"])

        for r in batches:
            held.append((r.column(0).to_numpy(zero_copy_only=False), r.column(1).to_numpy(zero_copy_only=False)))
            n += r.num_rows
            if n >= batch:
                yield flush()
                held, n = [], 0
        if held:
            yield flush()

    return links.mapInArrow(run, "u long, v long")


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges(a, b) -> (node, component): every node that has a link but the smallest ones, with the smallest node it reaches."""
    pairs = edges.select(F.col(edges.columns[0]).cast("long").alias("u"), F.col(edges.columns[1]).cast("long").alias("v")).where("u <> v")
    links = materialize(_local_forests(pairs).distinct(), "links")

    def signature(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.sum(F.xxhash64("u", "v") % 1_000_003), F.sum(F.xxhash64("v", "u") % 999_983)).first())

    before = signature(links)
    if before[0] == 0:
        return links.select(F.col("u").alias("node"), F.col("v").alias("component"))
    for _ in range(max_rounds):
        # large-star: v > u joins the smallest of u and its neighbours
        both = links.union(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # small-star: u and its smaller neighbours join the smallest of them; all links run downwards here
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        links = materialize(small.where("u <> v").distinct(), "links")
        after = signature(links)
        if after == before:
            return links.select(F.col("u").alias("node"), F.col("v").alias("component"))
        before = after
    raise RuntimeError("components did not settle")
