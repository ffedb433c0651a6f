"""Registered queries over parameters: chunk sides and bins, fanouts by the number of dimensions, generated arrays with
random components, orders of cells; and further operators around the arrays. Each with DuckDB SQL."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import partial, reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import ArrayQuery, Constraint
from ..operators import baselines as B
from ..operators import binning, linear
from ..operators import query as Q
from ..operators.tree import IndexConfig
from . import gauss
from .arrays import ARRAYS, PART_CELLS, cells_and_spec, index_of, load, ratio_query, ratio_sql, reduction, value_bounds, where_sql

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
_AE, _A2 = ARRAYS["ae"].sql, ARRAYS["a2"].sql


def add(name: str, f: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = f
    if sql:
        SQL[name] = sql


# ---- chunk sides, bins, fanouts ---------------------------------------------------------------------------------

_SIDES, _BINS = (12, 32), (4, 16)
_BAND = ("ae", ArrayQuery({"hour": Constraint.below(400)}, Constraint.between(20.0, 60.0)), "hour < 400 AND value >= 20.0 AND value < 60.0")


def chunk_bins_sweep(spark: SparkSession, d: str) -> DataFrame:
    """One query by chunk side and bins: the hits, and whether every leaf keeps to its bins."""
    out = []
    for side in _SIDES:
        for bins in _BINS:
            index = index_of(spark, d, "ae", IndexConfig(bins=bins, part_cells=PART_CELLS), (side, side))
            kept = index.leaves.agg((F.max(F.size("weights")) <= bins).alias("bins_kept"), F.count("*").alias("leaves"))
            hits = Q.range_query(index, _BAND[1]).agg(F.count("*").alias("hits"))
            out.append(hits.crossJoin(kept).select(F.lit(side).alias("side"), F.lit(bins).alias("bins"), "hits", "leaves", "bins_kept"))
    return reduce(DataFrame.union, out)


add("chunk_bins_sweep", chunk_bins_sweep, f"""WITH c AS (SELECT *, min("user") OVER () AS l0, min(hour) OVER () AS l1 FROM ({_AE})), s AS (SELECT unnest([12, 32]) AS side), l AS (SELECT side, count(DISTINCT (("user" - l0) // side, (hour - l1) // side)) AS leaves FROM c, s GROUP BY 1)
SELECT side, bins, (SELECT count(*) FROM ({where_sql(_BAND[0], _BAND[2])})) AS hits, leaves, true AS bins_kept FROM l, (SELECT unnest([4, 16]) AS bins)""")

#: Fanouts other than the default (8x8, 4x4x4, 4^4, 3^5).
_FANOUTS = (("a2", (4, 4)), ("a3", (2, 2, 2)), ("a4", (2, 2, 2, 2)), ("a5", (2,) * 5))


def fanout_by_dims(spark: SparkSession, d: str) -> DataFrame:
    out = []
    for array, fan in _FANOUTS:
        index = index_of(spark, d, array, IndexConfig(fanout=fan, part_cells=PART_CELLS))
        out.append(Q.range_query(index, ratio_query(index, 0.1)).agg(F.count("*").alias("hits")).select(F.lit(array).alias("array_name"), F.lit(math.prod(fan)).alias("fanout"), "hits"))
    return reduce(DataFrame.union, out)


add("fanout_by_dims", fanout_by_dims, " UNION ALL ".join(f"SELECT '{a}' AS array_name, {math.prod(f)} AS fanout, (SELECT count(*) FROM ({ratio_sql(a, 0.1)})) AS hits" for a, f in _FANOUTS))

# ---- sums of random Gaussians -----------------------------------------------------------------------------------

SHAPES = {2: (48, 48), 3: (18, 18, 18), 4: (9, 9, 9, 9)}
PARTS = {n: gauss.random_components(n, 4) for n in SHAPES}


def _level(n: int) -> float:
    """A fifth of the largest component's height: what lies below is empty in the sparse arrays."""
    return 0.2 * max(factor for _, _, factor in gauss.scaled(SHAPES[n], PARTS[n]))


def gauss_range(n: int, spark: SparkSession, d: str) -> DataFrame:
    """A range over a sparse array of full covariances; only chunks that hold a cell have a leaf."""
    index = gauss.index(spark, SHAPES[n], PARTS[n], threshold=_level(n))
    return Q.range_query(index, ArrayQuery({"d0": Constraint.between(2, SHAPES[n][0] - 2)}, Constraint.below(3 * _level(n)))).drop("value")


def gauss_ratio(n: int, hit: float) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        index = gauss.index(spark, SHAPES[n], PARTS[n])
        return Q.range_query(index, ratio_query(index, hit)).agg(F.count("*").alias("hits")).select(F.lit(n).alias("dims"), F.lit(hit).alias("hit"), "hits")

    return run


def _gauss_ratio_sql(n: int, hit: float) -> str:
    r = reduction(hit, n)
    box = " AND ".join(f"d{i} < {math.ceil(r * k)}" for i, k in enumerate(SHAPES[n]))
    value = "true" if hit >= 1 else f"value < vl + {r!r}::DOUBLE * (vh - vl)"
    return f"SELECT {n} AS dims, {hit}::DOUBLE AS hit, count(*) AS hits FROM (WITH g AS ({gauss.sql(SHAPES[n], PARTS[n], None)}), b AS (SELECT min(value) AS vl, max(value) AS vh FROM g) SELECT * FROM g, b WHERE {box} AND {value})"


for n in SHAPES:
    cells = f"WITH g AS ({gauss.sql(SHAPES[n], PARTS[n], None)}) SELECT {', '.join(f'd{i}' for i in range(n))} FROM g WHERE value >= {_level(n)!r}::DOUBLE"
    add(f"gauss_sparse_{n}d", partial(gauss_range, n), f"{cells} AND d0 >= 2 AND d0 < {SHAPES[n][0] - 2} AND value < {3 * _level(n)!r}::DOUBLE")
_RATIOS = (0.005, 0.1, 0.25, 0.5, 0.75, 1.0)
add("gauss_hit_ratios", lambda s, d: reduce(DataFrame.union, [gauss_ratio(n, h)(s, d) for n in SHAPES for h in _RATIOS]), " UNION ALL ".join(_gauss_ratio_sql(n, h) for n in SHAPES for h in _RATIOS))


def calibrated(spark: SparkSession, d: str, array: str = "a2p", wanted: tuple[float, ...] = (0.05, 0.3), rounds: int = 12) -> DataFrame:
    """Queries whose reduction is set by bisection on counted hits: the hit ratio comes within 0.02 of what is wanted."""
    index = index_of(spark, d, array)
    total = index.leaves.agg(F.sum("n_cells")).first()[0]
    low_value, high_value = value_bounds(index)
    out = []
    for h in wanted:
        lo, hi, hits = 0.0, 1.0, 0
        for _ in range(rounds):
            r = (lo + hi) / 2
            box = {x.name: Constraint.between(x.lo, x.lo + math.ceil(r * x.extent)) for x in index.spec.dims}
            hits = Q.range_query(index, ArrayQuery(box, Constraint.at_most(low_value + r * (high_value - low_value)))).count()
            if abs(hits / total - h) <= 0.01:
                break
            lo, hi = (r, hi) if hits / total < h else (lo, r)
        out.append((h, total, abs(hits / total - h) <= 0.02))
    return spark.createDataFrame(out, "wanted double, n_cells long, met boolean")


add("calibrated_hit_ratio", calibrated, f"SELECT unnest([0.05, 0.3])::DOUBLE AS wanted, (SELECT count(*) FROM ({ARRAYS['a2p'].sql})) AS n_cells, true AS met")

# ---- orders of cells --------------------------------------------------------------------------------------------

_CHUNKS = "WITH RECURSIVE c AS (SELECT *, min(partkey) OVER () AS l0, min(suppkey) OVER () AS l1 FROM ({})), k AS (SELECT DISTINCT (partkey - l0) // 32 AS c0, (suppkey - l1) // 32 AS c1 FROM c)".format(_A2)


def _walk(start: str, bits: int) -> str:
    """Table h(c0, c1, h): the Hilbert code of start's c0 and c1, bit by bit from the highest."""
    top = (1 << bits) - 1
    return f"""w AS (SELECT c0, c1, c0 AS x, c1 AS y, CAST({1 << (bits - 1)} AS BIGINT) AS s, CAST(0 AS BIGINT) AS h FROM {start} UNION ALL SELECT c0, c1,
CASE WHEN y & s > 0 THEN x WHEN x & s > 0 THEN {top} - y ELSE y END, CASE WHEN y & s > 0 THEN y WHEN x & s > 0 THEN {top} - x ELSE x END, s // 2, h + s * s * (CASE WHEN x & s > 0 THEN (CASE WHEN y & s > 0 THEN 2 ELSE 3 END) ELSE (CASE WHEN y & s > 0 THEN 1 ELSE 0 END) END) FROM w WHERE s > 0)"""


add("hilbert_codes", lambda s, d: linear.chunk_synopsis(*cells_and_spec(s, d, "a2")).select("c0", "c1", linear.hilbert_code([F.col("c0"), F.col("c1")], 12).alias("h")), f"{_CHUNKS}, {_walk('k', 12)} SELECT c0, c1, h FROM w WHERE s = 0")
_ORDER_BITS = " + ".join(f"((c0 >> {j}) & 1) * {1 << (2 * j + 1)} + ((c1 >> {j}) & 1) * {1 << (2 * j)}" for j in range(16))


def order_runs(spark: SparkSession, d: str) -> DataFrame:
    """Runs of ones of one column's bitmap when cells lie in row-major, Z or Hilbert order: what a run-length code meets."""
    cells, spec = cells_and_spec(spark, d, "a2")
    at = [F.col(x.name) - F.lit(x.lo) for x in spec.dims]
    codes = {"row_major": linear.row_major(at, [1 << 16, 1 << 16]), "z": linear.interleave(at, 16), "hilbert": linear.hilbert_code(at, 16)}
    ones = cells.where(at[1] < 16)
    out = []
    for name, code in codes.items():
        p = ones.select(code.alias("at"))
        starts = p.join(p.select((F.col("at") + 1).alias("at")), "at", "left_anti")
        out.append(starts.agg(F.count("*").alias("runs")).select(F.lit(name).alias("cell_order"), "runs"))
    return reduce(DataFrame.union, out)


add("order_runs", order_runs, f"""WITH RECURSIVE c AS (SELECT *, min(partkey) OVER () AS l0, min(suppkey) OVER () AS l1 FROM ({_A2})), k AS (SELECT partkey - l0 AS c0, suppkey - l1 AS c1 FROM c WHERE suppkey - l1 < 16), {_walk('k', 16)},
p AS (SELECT 'row_major' AS cell_order, c0 * 65536 + c1 AS at FROM k UNION ALL SELECT 'z', {_ORDER_BITS} FROM k UNION ALL SELECT 'hilbert', h FROM w WHERE s = 0)
SELECT cell_order, count(*) AS runs FROM p WHERE NOT EXISTS (SELECT 1 FROM p q WHERE q.cell_order = p.cell_order AND q.at = p.at - 1) GROUP BY 1""")

# ---- more operators around the arrays ---------------------------------------------------------------------------


def synopsis_histogram(spark: SparkSession, d: str) -> DataFrame:
    """Each chunk's synopsis with a histogram of eight equal intervals."""
    cells, spec = cells_and_spec(spark, d, "ae")
    return linear.chunk_synopsis(cells, spec, histogram=8).select("c0", "c1", "n_cells", "vmin", "vmax", F.posexplode("histogram").alias("bin_no", "n")).where("n > 0")


add("synopsis_histogram", synopsis_histogram, f'WITH c AS (SELECT *, min("user") OVER () AS l0, min(hour) OVER () AS l1 FROM ({_AE})), k AS (SELECT *, ("user" - l0) // 16 AS c0, (hour - l1) // 16 AS c1 FROM c), m AS (SELECT c0, c1, count(*) AS n_cells, min(value) AS vmin, max(value) AS vmax FROM k GROUP BY 1, 2) SELECT c0, c1, n_cells, vmin, vmax, CAST(coalesce(least(floor((value - vmin) * 8 / nullif(vmax - vmin, 0.0)), 7), 0) AS BIGINT) AS bin_no, count(*) AS n FROM k JOIN m USING (c0, c1) GROUP BY ALL')


def assigned_bins(spark: SparkSession, d: str) -> DataFrame:
    """Values meet bins by a range join."""
    bands = spark.createDataFrame([(k, 12.5 * k, 12.5 * (k + 1)) for k in range(8)], "bin_no int, lo double, hi double")
    return binning.assign_bins(cells_and_spec(spark, d, "ae")[0], "value", bands).groupBy("bin_no").agg(F.count("*").alias("n"), F.max("value").alias("top"))


add("assigned_bins", assigned_bins, f"SELECT CAST(floor(value / 12.5) AS INTEGER) AS bin_no, count(*) AS n, max(value) AS top FROM ({_AE}) WHERE value >= 0 AND value < 100 GROUP BY 1")


def distinct_values(spark: SparkSession, d: str) -> DataFrame:
    """Distinct values by user, exact, and the sketch's count within a tenth of it (or two)."""
    rows = load(spark, d, "events").groupBy("user_id").agg(F.countDistinct("value").alias("exact"), F.approx_count_distinct("value", 0.02).alias("near"))
    return rows.select("user_id", "exact", (F.abs(F.col("near") - F.col("exact")) <= F.greatest(F.lit(2.0), F.col("exact") * 0.1)).alias("close"))


add("distinct_values", distinct_values, "SELECT user_id, count(DISTINCT value) AS exact, true AS close FROM events GROUP BY 1")


def quantile_sketches(spark: SparkSession, d: str) -> DataFrame:
    """The exact median of all values, and whether the ranks of approximate ones are within 2 %."""
    cells = cells_and_spec(spark, d, "ae")[0]
    q = cells.agg(F.percentile("value", 0.5).alias("median"), F.percentile_approx("value", 0.5, 1000).alias("near"))
    ranked = cells.crossJoin(F.broadcast(q)).agg(F.first("median").alias("median"), F.avg((F.col("value") <= F.col("near")).cast("double")).alias("share"), F.avg((F.col("value") < F.col("near")).cast("double")).alias("under"))
    return ranked.select("median", ((F.col("share") >= 0.48) & (F.col("under") <= 0.52)).alias("close"))


add("quantile_sketches", quantile_sketches, f"SELECT quantile_cont(value, 0.5) AS median, true AS close FROM ({_AE})")
add("grouping_sets", lambda s, d: (load(s, d, "orders").createOrReplaceTempView("gridmask_orders"), s.sql("SELECT o_orderstatus, year(o_orderdate) AS y, count(*) AS n, max(o_totalprice) AS top FROM gridmask_orders GROUP BY GROUPING SETS ((o_orderstatus), (year(o_orderdate)), ())"))[1], "SELECT o_orderstatus, y, count(*) AS n, max(o_totalprice) AS top FROM (SELECT *, year(o_orderdate) AS y FROM orders) GROUP BY GROUPING SETS ((o_orderstatus), (y), ())")


def rankings(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("nation").orderBy(F.desc("value"), "cust")
    cells = cells_and_spec(spark, d, "ak")[0]
    return cells.select("nation", "cust", F.rank().over(w).alias("place"), F.dense_rank().over(Window.partitionBy("nation").orderBy(F.floor(F.col("value") / 1000))).alias("tier"), F.ntile(4).over(w).alias("quarter"))


add("rankings", rankings, f"SELECT nation, cust, rank() OVER w AS place, dense_rank() OVER (PARTITION BY nation ORDER BY floor(value / 1000)) AS tier, ntile(4) OVER w AS quarter FROM ({ARRAYS['ak'].sql}) WINDOW w AS (PARTITION BY nation ORDER BY value DESC, cust)")
add("string_scalars", lambda s, d: load(s, d, "pages").select("page_id", F.length("html").alias("n"), F.lower(F.substring("html", 1, 5)).alias("head"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("padded"), F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.upper(F.trim("url")).alias("loud")), "SELECT page_id, length(html) AS n, lower(substring(html, 1, 5)) AS head, lpad(CAST(page_id AS VARCHAR), 8, '0') AS padded, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, upper(trim(url)) AS loud FROM pages")


def zipped_weights(spark: SparkSession, d: str) -> DataFrame:
    """Bin -> weight maps of two halves of the hours, added key by key."""
    cells, spec = cells_and_spec(spark, d, "ae")
    middle = spec.dims[1].lo + spec.dims[1].extent // 2
    binned = cells.select("user", (F.col("hour") < middle).alias("early"), F.floor(F.col("value") / 25).alias("bin")).groupBy("user", "early", "bin").agg(F.count("*").alias("n"))
    maps = binned.groupBy("user", "early").agg(F.map_from_entries(F.collect_list(F.struct("bin", "n"))).alias("m"))
    none = F.create_map().cast("map<bigint,bigint>")
    both = maps.groupBy("user").agg(F.coalesce(F.max_by("m", F.when(F.col("early"), 1)), none).alias("a"), F.coalesce(F.max_by("m", F.when(~F.col("early"), 1)), none).alias("b"))
    zipped = F.map_zip_with("a", "b", lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))
    return both.select("user", F.explode(zipped).alias("bin", "n"))


add("zipped_weights", zipped_weights, f'SELECT "user", CAST(floor(value / 25) AS BIGINT) AS bin, count(*) AS n FROM ({_AE}) GROUP BY 1, 2')


def stored_order(spark: SparkSession, d: str) -> DataFrame:
    """Cells of each stored part: their number, and whether its files hold no code of another part."""
    index = index_of(spark, d, "a2", IndexConfig(part_cells=256))
    rows = index._load("cells", None).groupBy("part").agg(F.count("*").alias("n"), F.min("z").alias("a"), F.max("z").alias("b"))
    own = (F.shiftright("a", index.shift) == F.col("part")) & (F.shiftright("b", index.shift) == F.col("part"))
    return rows.agg(F.sum("n").alias("n"), F.min(own).alias("apart"))


add("stored_order", stored_order, f"SELECT count(*) AS n, true AS apart FROM ({_A2})")


def full_grid_ratio(spark: SparkSession, d: str) -> DataFrame:
    """Hits over the cells that are there, and over the whole grid."""
    out = []
    for a in ("a2", "ae"):
        index = index_of(spark, d, a)
        grid = math.prod(x.extent for x in index.spec.dims)
        total = index.leaves.agg(F.sum("n_cells").alias("n"))
        hits = Q.range_query(index, ratio_query(index, 0.25)).agg(F.count("*").alias("hits"))
        out.append(total.crossJoin(hits).select(F.lit(a).alias("array_name"), (F.col("hits") / F.col("n")).alias("of_cells"), (F.col("hits") / F.lit(float(grid))).alias("of_grid")))
    return reduce(DataFrame.union, out)


def _grid_sql(a: str) -> str:
    dims = ARRAYS[a].dims
    grid = " * ".join(f'(max("{x}") - min("{x}") + 1)' for x in dims)
    return f"SELECT '{a}' AS array_name, h.hits / g.n AS of_cells, h.hits / g.grid AS of_grid FROM (SELECT count(*) AS hits FROM ({ratio_sql(a, 0.25)})) h, (SELECT count(*) AS n, CAST({grid} AS DOUBLE) AS grid FROM ({ARRAYS[a].sql})) g"


add("full_grid_ratio", full_grid_ratio, " UNION ALL ".join(map(_grid_sql, ("a2", "ae"))))


def bin_reduction(spark: SparkSession, d: str) -> DataFrame:
    """Bitmaps that a range reads at most: of 16 adaptive bins a leaf, and of 32 global ones."""
    leaves = index_of(spark, d, "ae", IndexConfig(leaf_encoding="range", codec="raw", list_below=0)).leaves
    most = leaves.agg(F.max(F.size("bitmaps")).alias("tree_bitmaps"))
    cells, spec = cells_and_spec(spark, d, "ae")
    edges = B.global_edges(cells, ["value"], 32)["value"]
    return most.select("tree_bitmaps", F.lit(int(np.size(edges) - 2)).alias("global_bitmaps"))


add("bin_reduction", bin_reduction, "SELECT 15 AS tree_bitmaps, 31 AS global_bitmaps")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)
