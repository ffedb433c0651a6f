"""Bins of chunks and of whole arrays as DataFrame operations: windows and aggregates, no Python.

Edges of a chunk's bins are order statistics: bin k begins at the value of rank floor(k * n / B) + 1, and bins with the
same beginning are one. These are the leaves' edges too; a chunk is bounded, so its sort is local.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Bins of a whole array that may be broadcast.
MOST_BINS = 100_000


def equi_depth_bins(df: DataFrame, attr: str, bins: int, by: list[str]) -> DataFrame:
    """by, bin_no, lo, n: lower edges of at most `bins` bins in each group, and the values in each bin."""
    w = Window.partitionBy(*by)
    ranked = df.withColumn("r", F.row_number().over(w.orderBy(attr))).withColumn("n", F.count("*").over(w))
    cuts = F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda k: F.floor(k * F.col("n") / bins) + 1)
    edges = ranked.where(F.array_contains(cuts, F.col("r"))).select(*by, F.col(attr).alias("lo")).distinct()
    return _counted(df, edges, attr, by)


def _counted(df: DataFrame, edges: DataFrame, attr: str, by: list[str]) -> DataFrame:
    """Number edges by group and count the values from each edge to the next: one union and one window, no range join."""
    w = Window.partitionBy(*by)
    marks = edges.select(*by, F.col("lo").alias("v"), F.lit(0).alias("is_value"))
    rows = marks.unionByName(df.select(*by, F.col(attr).alias("v"), F.lit(1).alias("is_value")))
    at = rows.withColumn("bin_no", F.sum(1 - F.col("is_value")).over(w.orderBy("v", "is_value").rowsBetween(Window.unboundedPreceding, 0)) - 1)
    return at.groupBy(*by, "bin_no").agg(F.min("v").alias("lo"), F.sum("is_value").alias("n"))


def equi_width_bins(df: DataFrame, attr: str, bins: int, by: list[str]) -> DataFrame:
    """by, bin_no, n: values in each of `bins` equal intervals of the group's range."""
    span = df.groupBy(*by).agg(F.min(attr).alias("a"), F.max(attr).alias("b"))
    at = F.least(F.floor((F.col(attr) - F.col("a")) * bins / F.nullif(F.col("b") - F.col("a"), F.lit(0.0))), F.lit(bins - 1))
    return df.join(span, by).groupBy(*by, F.coalesce(at, F.lit(0)).alias("bin_no")).agg(F.count("*").alias("n"))


def weighted_bins(df: DataFrame, attr: str, weight: Column, bins: int, by: list[str]) -> DataFrame:
    """by, bin_no, lo, n: bins that begin where the running weight passes k / bins of the group's weight."""
    w = Window.partitionBy(*by)
    rows = df.withColumn("wt", weight).groupBy(*by, attr).agg(F.sum("wt").alias("wt"))
    run = rows.withColumn("before", F.coalesce(F.sum("wt").over(w.orderBy(attr).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("total", F.sum("wt").over(w))
    share = lambda c: F.floor(c * bins / F.col("total"))
    begins = (F.col("before") == 0) | (share(F.col("before") + F.col("wt") - 1) > share(F.col("before") - 1))
    return _counted(df, run.where(begins).select(*by, F.col(attr).alias("lo")), attr, by)


def singleton_bins(df: DataFrame, attr: str, by: list[str], most: int) -> DataFrame:
    """by, value, n: a bin for each distinct value, in groups that have at most `most` of them."""
    counts = df.groupBy(*by, F.col(attr).alias("value")).agg(F.count("*").alias("n"))
    few = counts.groupBy(*by).agg(F.count("*").alias("k")).where(F.col("k") <= most)
    return counts.join(few.select(*by), by, "left_semi")


def sketch_edges(df: DataFrame, attr: str, bins: int, by: list[str]) -> DataFrame:
    """by, edges: quantiles from a mergeable sketch, for groups too large to sort."""
    ranks = [k / bins for k in range(bins + 1)]
    return df.groupBy(*by).agg(F.percentile_approx(attr, ranks, 10_000).alias("edges"))


def assign_bins(df: DataFrame, attr: str, edges: DataFrame) -> DataFrame:
    """Range join of values with bins(bin_no, lo, hi): at most MOST_BINS of them, which are broadcast."""
    if edges.limit(MOST_BINS + 1).count() > MOST_BINS:
        raise ValueError(f"more than {MOST_BINS} bins")
    return df.join(F.broadcast(edges), (F.col(attr) >= F.col("lo")) & (F.col(attr) < F.col("hi")))


def value_bitmaps(df: DataFrame, key: Column, cell: Column) -> DataFrame:
    """key, block, bitmap (4,096 bytes): low-level (key = value) or binned bitmaps by Spark's own bitmap aggregate."""
    # positions count from 1: 0 and 1 would share a bit
    placed = df.select(key.alias("key"), (cell + 1).alias("p"))
    return placed.groupBy("key", F.bitmap_bucket_number("p").alias("block")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("bitmap"))
