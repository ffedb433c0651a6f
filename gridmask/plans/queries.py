"""Registered queries of the array engine, each with DuckDB SQL over the same tables where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import edges as E
from ..model import ArrayQuery, Constraint, complete_query, fit_spec
from ..operators import append as A
from ..operators import baselines as B
from ..operators import binning, linear
from ..operators import query as Q
from ..operators.tree import Index, IndexConfig, build_index, choose_fanout, read_index, written
from . import gauss
from .arrays import ARRAYS, PART_CELLS, cells_and_spec, index_of, linear_of, load, ratio_query, ratio_sql, reduction, where_sql

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def add(name: str, f: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    query(name, sql)(f)


# ---- range queries at several hit ratios ------------------------------------------------------------------------

HITS = {"005": 0.005, "10": 0.1, "25": 0.25, "50": 0.5, "75": 0.75, "100": 1.0}


def by_ratio(array: str, hit: float, spark: SparkSession, d: str) -> DataFrame:
    index = index_of(spark, d, array)
    return Q.range_query(index, ratio_query(index, hit))


for tag, hit in HITS.items():
    for label, array in (("2d", "a2"), ("3d", "a3"), ("4d", "a4")):
        add(f"range_{label}_{tag}", partial(by_ratio, array, hit), ratio_sql(array, hit))
for tag in ("005", "10", "50", "100"):
    add(f"smooth_range_{tag}", partial(by_ratio, "a2p", HITS[tag]), ratio_sql("a2p", HITS[tag]))
add("range_5d_10", partial(by_ratio, "a5", 0.1), ratio_sql("a5", 0.1))
add("dense_embeddings_range", partial(by_ratio, "av", 0.1), ratio_sql("av", 0.1))
add("sparse_orders_range", partial(by_ratio, "ao", 0.25), ratio_sql("ao", 0.25))
add("events_range", partial(by_ratio, "ae", 0.25), ratio_sql("ae", 0.25))
add("conversation_range", partial(by_ratio, "ac", 0.5), ratio_sql("ac", 0.5))
add("document_range_1d", partial(by_ratio, "ad", 0.25), ratio_sql("ad", 0.25))
add("customer_range", partial(by_ratio, "ak", 0.5), ratio_sql("ak", 0.5))
add("tiny_array_range", partial(by_ratio, "ag", 0.5), ratio_sql("ag", 0.5))
add("constant_array_range", partial(by_ratio, "an", 1.0), ratio_sql("an", 1.0))


def fixed(array: str, q: ArrayQuery, spark: SparkSession, d: str, **options) -> DataFrame:
    return Q.range_query(index_of(spark, d, array), q, **options)


C = Constraint
FIXED: dict[str, tuple[str, ArrayQuery, str]] = {
    "mixed_satellite_style": ("a3", ArrayQuery({"partkey": C.between(20, 700), "suppkey": C.between(2, 60)}, C.at_least(30000.0)), "partkey >= 20 AND partkey < 700 AND suppkey >= 2 AND suppkey < 60 AND value >= 30000.0"),
    "one_sided": ("ae", ArrayQuery({"hour": C.below(400)}, C.between(20.0, 60.0)), "hour < 400 AND value >= 20.0 AND value < 60.0"),
    "attr_only": ("a2", ArrayQuery({}, C.between(20000.0, 30000.0, hi_incl=True)), "value >= 20000.0 AND value <= 30000.0"),
    "dim_only": ("a2", ArrayQuery({"partkey": C.between(33, 129), "suppkey": C.at_least(5)}), "partkey >= 33 AND partkey < 129 AND suppkey >= 5"),
    "point_query": ("aet", ArrayQuery({"user": C.between(0, 80)}, C.eq(2.0)), "\"user\" < 80 AND value = 2.0"),
    "empty_result": ("a2", ArrayQuery({"partkey": C.between(10, 20)}, C.at_least(1e12)), "partkey >= 10 AND partkey < 20 AND value >= 1e12"),
    "outside_domain": ("a2", ArrayQuery({"partkey": C.between(-50, 64), "suppkey": C.between(8, 10**6)}), "partkey < 64 AND suppkey >= 8"),
    "chunk_borders": ("a2", ArrayQuery({"partkey": C.between(33, 97), "suppkey": C.between(1, 33)}), "partkey >= 33 AND partkey < 97 AND suppkey >= 1 AND suppkey < 33"),
    "exclusive_bounds": ("ak", ArrayQuery({"cust": C(10, 1000, False, True)}, C(0.0, 5000.0, False, False)), "cust > 10 AND cust <= 1000 AND value > 0.0 AND value < 5000.0"),
    "member_attr": ("aet", ArrayQuery({}, C.isin([0.0, 3.0])), "value IN (0.0, 3.0)"),
    "member_dim": ("a2", ArrayQuery({"suppkey": C.isin([1, 2, 3, 7, 9, 40])}, C.below(40000.0)), "suppkey IN (1, 2, 3, 7, 9, 40) AND value < 40000.0"),
    "member_both": ("ap", ArrayQuery({"brand": C.isin([0, 4, 5, 19])}, C.between(950.0, 1010.0)), "brand IN (0, 4, 5, 19) AND value >= 950.0 AND value < 1010.0"),
    "label_equality": ("al", ArrayQuery({}, C.eq(1.0)), "value = 1.0"),
}
for name, (array, q, condition) in FIXED.items():
    # sets go by the bitmaps and masks made for them
    add(name, partial(fixed, array, q, leaves="bitmaps" if name.startswith(("member", "point", "label")) else "values"), where_sql(array, condition))
for array in ("a2p", "ae", "a3"):
    for tag in ("10", "50"):
        add(f"count_{array}_{tag}", lambda s, d, a=array, h=HITS[tag]: (lambda i: Q.count_query(i, ratio_query(i, h)))(index_of(s, d, a)), f"SELECT count(*) AS hits FROM ({ratio_sql(array, HITS[tag])})")
    add(f"bitmap_leaves_{array}", lambda s, d, a=array: (lambda i: Q.range_query(i, ratio_query(i, 0.1), leaves="bitmaps"))(index_of(s, d, a)), ratio_sql(array, 0.1))
add("aligned_bounds_bucket_form", partial(fixed, "a2", FIXED["chunk_borders"][1], exact=False, leaves="bitmaps"), where_sql("a2", FIXED["chunk_borders"][2]))

for enc, codec in (("equality", "raw"), ("equality", "wah"), ("range", "raw"), ("range", "bbc"), ("range", "wordrun"), ("interval", "wah"), ("interval", "wordrun"), ("bit_sliced", "raw"), ("components", "wah"), ("two_level", "wah")):
    cfg = IndexConfig(leaf_encoding=enc, codec=codec, list_below=0)
    add(f"leaf_{enc}_{codec}", lambda s, d, cfg=cfg: Q.range_query(index_of(s, d, "ae", cfg), FIXED["one_sided"][1], leaves="bitmaps"), where_sql("ae", FIXED["one_sided"][2]))
for rule in ("equi_width", "optimal", "v_uniform", "v_normal", "by_sign"):
    cfg = IndexConfig(bins=4, merge=rule)
    add(f"merge_{rule}_range", lambda s, d, cfg=cfg: Q.range_query(index_of(s, d, "a2p", cfg), ArrayQuery({"partkey": C.between(5, 900)}, C.between(930.0, 980.0))), where_sql("a2p", "partkey >= 5 AND partkey < 900 AND value >= 930.0 AND value < 980.0"))
for rule in ("equi_width", "v_optimal", "weighted"):
    cfg = IndexConfig(leaf_binning=rule, list_below=0, query_weights=((20.0, 60.0, 9.0),))
    add(f"leaf_bins_{rule}_range", lambda s, d, cfg=cfg: Q.range_query(index_of(s, d, "ae", cfg), FIXED["one_sided"][1], leaves="bitmaps"), where_sql("ae", FIXED["one_sided"][2]))
for tag, fan in (("2", (2, 2)), ("4", (4, 4)), ("16", (16, 16))):
    add(f"fanout_{tag}_range", lambda s, d, fan=fan: (lambda i: Q.range_query(i, ratio_query(i, 0.1)))(index_of(s, d, "ae", IndexConfig(fanout=fan))), ratio_sql("ae", 0.1))
add("list_leaves", lambda s, d: Q.range_query(index_of(s, d, "ao", IndexConfig(list_below=10**9)), ArrayQuery({"cust": C.below(700)}, C.at_least(100000.0)), leaves="bitmaps"), where_sql("ao", "cust < 700 AND value >= 100000.0"))


for order in ("row", "hilbert"):
    cfg = IndexConfig(node_order=order, part_cells=PART_CELLS)
    add(f"node_order_{order}", lambda s, d, cfg=cfg: (lambda i: Q.range_query(i, ratio_query(i, 0.1)))(index_of(s, d, "a2p", cfg)), ratio_sql("a2p", 0.1))


def by_tables(array: str, hit: float, spark: SparkSession, d: str) -> DataFrame:
    """The descent whose frontier is never held by the driver."""
    index = index_of(spark, d, array, IndexConfig(part_cells=PART_CELLS, bins=8))
    index.dense_rows = 0
    return Q.range_query(index, ratio_query(index, hit))


for label, array, hit in (("2d_005", "a2p", 0.005), ("2d_50", "a2p", 0.5), ("3d_10", "a3", 0.1)):
    add(f"frontier_tables_{label}", partial(by_tables, array, hit), ratio_sql(array, hit))


@query("multi_attr", f"SELECT a.partkey, a.suppkey, a.value, b.value AS quantity FROM ({ARRAYS['a2'].sql}) a JOIN ({ARRAYS['a2q'].sql}) b USING (partkey, suppkey) WHERE a.value >= 20000.0 AND a.value < 60000.0 AND b.value >= 10.0 AND b.value < 30.0 AND partkey < 900")
def multi_attr(spark: SparkSession, d: str) -> DataFrame:
    box = {"partkey": C.below(900)}
    return Q.range_query_multi([("value", index_of(spark, d, "a2"), ArrayQuery(box, C.between(20000.0, 60000.0))), ("quantity", index_of(spark, d, "a2q"), ArrayQuery(box, C.between(10.0, 30.0)))])


_BOXES = [(k, (k * 37) % 900, (k * 37) % 900 + 60 + 5 * k, (k * 11) % 50, (k * 11) % 50 + 12, 1000.0 * k, 1000.0 * k + 25000.0) for k in range(20)]


@query("batch_queries", f"SELECT q, partkey, suppkey, value FROM ({ARRAYS['a2'].sql}) JOIN (VALUES {', '.join(map(str, _BOXES))}) b(q, pl, ph, sl, sh, vl, vh) ON partkey >= pl AND partkey < ph AND suppkey >= sl AND suppkey < sh AND value >= vl AND value < vh")
def batch_queries(spark: SparkSession, d: str) -> DataFrame:
    boxes = spark.createDataFrame(_BOXES, "q int, lo_partkey long, hi_partkey long, lo_suppkey long, hi_suppkey long, lo_value double, hi_value double")
    return Q.batch_query(index_of(spark, d, "a2"), boxes)


#: More bins than a node's children have bounds: nothing is merged, so masks are exact.
_EXACT = IndexConfig(bins=200, part_cells=PART_CELLS)


def levels_sql(condition: str, inside: str, side: int = 32, fan: int = 8, most: int = 6) -> tuple[str, str]:
    """CTEs over a2p up to a table s(level, c0, c1, n, whole, meets): each node's cells, and whether it lies inside the query
    or meets it; and the condition that the level is below the root. Boxes are clipped by the array's shape.

    condition names cells(partkey, suppkey, value), bounds l0, l1, h0, h1, vl, vh and the query's ends q0, q1, qv
    (exclusive) and p0, p1; inside is the test of a range of values [vmin, vmax] against the query."""
    parts = f"""WITH c AS ({ARRAYS['a2p'].sql}), b AS (SELECT min(partkey) AS l0, max(partkey) + 1 AS h0, min(suppkey) AS l1, max(suppkey) + 1 AS h1, min(value) AS vl, max(value) AS vh FROM c), q AS (SELECT *, {condition} FROM b),
t AS (SELECT (partkey - l0) // {side} AS c0, (suppkey - l1) // {side} AS c1, count(*) AS n, min(value) AS vmin, max(value) AS vmax FROM c, b GROUP BY 1, 2),
h AS (SELECT min(k) AS height FROM b, (SELECT unnest(generate_series(1, {most})) AS k) WHERE {fan}**k * {side} >= h0 - l0 AND {fan}**k * {side} >= h1 - l1),
u AS (SELECT k AS level, c0 // CAST({fan}**k AS BIGINT) AS c0, c1 // CAST({fan}**k AS BIGINT) AS c1, sum(n) AS n, min(vmin) AS vmin, max(vmax) AS vmax FROM t, (SELECT unnest(generate_series(0, {most})) AS k) GROUP BY 1, 2, 3),
e AS (SELECT u.*, q.*, l0 + c0 * CAST({side} * {fan}**level AS BIGINT) AS a0, least(h0, l0 + (c0 + 1) * CAST({side} * {fan}**level AS BIGINT)) AS b0, l1 + c1 * CAST({side} * {fan}**level AS BIGINT) AS a1, least(h1, l1 + (c1 + 1) * CAST({side} * {fan}**level AS BIGINT)) AS b1 FROM u, q),
s AS (SELECT level, c0, c1, n, vmin, vmax, a0 >= p0 AND b0 <= q0 AND a1 >= p1 AND b1 <= q1 AND {inside} AS whole, a0 < q0 AND b0 > p0 AND a1 < q1 AND b1 > p1 AND vmin < qv AS meets FROM e)"""
    return parts, "level < (SELECT height FROM h)"


_PROGRESS = levels_sql("800 AS q0, h1 AS q1, 960.0 AS qv, 20 AS p0, l1 AS p1", "vmax < qv")


@query("progressive_levels", _PROGRESS[0] + ", top AS (SELECT c0, c1, level FROM s WHERE whole AND " + _PROGRESS[1] + "), k AS (SELECT partkey, suppkey, value, max(top.level) AS level FROM c, b, top WHERE (partkey - l0) // CAST(32 * 8**top.level AS BIGINT) = top.c0 AND (suppkey - l1) // CAST(32 * 8**top.level AS BIGINT) = top.c1 GROUP BY 1, 2, 3) SELECT coalesce(k.level, -1) AS level, partkey, suppkey, value FROM c LEFT JOIN k USING (partkey, suppkey, value) WHERE partkey >= 20 AND partkey < 800 AND value < 960.0")
def progressive_levels(spark: SparkSession, d: str) -> DataFrame:
    """Hits with the level of the node that told them (-1: verified by their value)."""
    q = ArrayQuery({"partkey": C.between(20, 800)}, C.below(960.0))
    return Q.progressive(index_of(spark, d, "a2p", _EXACT), q)


# ---- estimates and counters -------------------------------------------------------------------------------------

_EST = ("a2p", ArrayQuery({"partkey": C.between(20, 800)}, C.below(960.0)), "partkey >= 20 AND partkey < 800 AND value < 960.0")


@query("estimate_bounds", f"SELECT levels, count(*) FILTER (WHERE {_EST[2]}) AS exact, true AS within FROM ({ARRAYS['a2p'].sql}), (VALUES (1), (2)) v(levels) GROUP BY levels")
def estimate_bounds(spark: SparkSession, d: str) -> DataFrame:
    index = index_of(spark, d, _EST[0])
    exact = Q.range_query(index, _EST[1]).agg(F.count("*").alias("exact"))
    rows = [Q.estimate_count(index, _EST[1], k).withColumn("levels", F.lit(k)) for k in (1, 2)]
    return reduce(DataFrame.union, rows).crossJoin(exact).select("levels", "exact", ((F.col("lower_bound") <= F.col("exact")) & (F.col("exact") <= F.col("upper_bound"))).alias("within"))


_EXACT_COUNT = f"SELECT count(*) AS exact, true AS within FROM ({where_sql(_EST[0], _EST[2])})"


@query("estimate_error", f"SELECT levels, exact, within FROM ({_EXACT_COUNT}), (VALUES (1), (2)) v(levels)")
def estimate_error(spark: SparkSession, d: str) -> DataFrame:
    """Estimates level by level: within the count's bounds, the sum within the bounds times the largest value, and the
    mean within the values asked for."""
    index = index_of(spark, d, _EST[0])
    exact = Q.range_query(index, _EST[1]).agg(F.count("*").alias("exact"), F.sum("value").alias("total"))
    rows = []
    for k in (1, 2):
        both = Q.estimate_agg(index, _EST[1], k).crossJoin(Q.estimate_count(index, _EST[1], k)).crossJoin(exact)
        count_ok = (F.col("est_count") >= F.col("lower_bound") - 1e-6) & (F.col("est_count") <= F.col("upper_bound") + 1e-6)
        spread = F.col("upper_bound") - F.col("lower_bound")
        sum_ok = F.abs(F.col("est_sum") - F.col("total")) <= spread * 960.0 + F.col("total") * 0.05
        rows.append(both.select(F.lit(k).alias("levels"), "exact", (count_ok & sum_ok & ((F.col("exact") == 0) | F.col("est_avg").between(900.0, 960.0))).alias("within")))
    return reduce(DataFrame.union, rows)


@query("estimate_members", f"SELECT levels, value, count(*) AS est FROM ({ARRAYS['aet'].sql}), (VALUES (1), (2)) v(levels) WHERE value IN (0.0, 2.0, 4.0) GROUP BY 1, 2")
def estimate_members(spark: SparkSession, d: str) -> DataFrame:
    """Equality on few values: bins are the values themselves, so estimates are exact on every level."""
    index = index_of(spark, d, "aet")
    rows = [Q.estimate_agg(index, ArrayQuery({}, C.eq(v)), k).select(F.lit(k).alias("levels"), F.lit(v).alias("value"), F.round("est_count").cast("long").alias("est")) for k in (1, 2) for v in (0.0, 2.0, 4.0)]
    return reduce(DataFrame.union, rows).where("est > 0")


@query("estimate_from_histograms", f"SELECT count(*) AS exact, true AS within FROM ({where_sql('ae', 'value >= 20.0 AND value < 60.0')})")
def estimate_from_histograms(spark: SparkSession, d: str) -> DataFrame:
    """From the chunks' histograms alone: off by at most the cells of two bins in each chunk, of an equal share each."""
    index, q = index_of(spark, d, "ae"), ArrayQuery({}, C.between(20.0, 60.0))
    leaves = index.leaves.agg(F.sum(F.col("n_cells") * 2 / 16 + 2).alias("slack"))
    exact = Q.range_query(index, q).agg(F.count("*").alias("exact"))
    both = Q.estimate_from_histograms(index, q).crossJoin(leaves).crossJoin(exact)
    return both.select("exact", (F.abs(F.col("est_count") - F.col("exact")) <= F.col("slack")).alias("within"))


@query("estimate_from_bins", f"SELECT count(*) AS exact, true AS within FROM ({where_sql('a2', 'partkey >= 33 AND partkey < 129 AND value >= 20000.0 AND value < 50000.0')})")
def estimate_from_bins(spark: SparkSession, d: str) -> DataFrame:
    """Bounds from the global bitmaps alone; the edge bins of both columns make up what lies between them."""
    wanted = {"partkey": [C.between(33, 129)], "value": [C.between(20000.0, 50000.0)]}
    index = linear_of(spark, d, "a2", "all")
    exact = B.bitmap_hits(index, wanted).agg(F.count("*").alias("exact"))
    return B.count_bounds(index, wanted).crossJoin(exact).select("exact", ((F.col("lower_bound") <= F.col("exact")) & (F.col("exact") <= F.col("upper_bound")) & (F.col("upper_bound") > 0)).alias("within"))


def _trace_sql(hit: float) -> str:
    r = ratio_reduction(hit)
    ends = f"l0 + CAST(ceil({r}::DOUBLE * (h0 - l0)) AS BIGINT) AS q0, l1 + CAST(ceil({r}::DOUBLE * (h1 - l1)) AS BIGINT) AS q1, {'vh + 1' if hit >= 1 else f'vl + {r}::DOUBLE * (vh - vl)'} AS qv, l0 AS p0, l1 AS p1"
    parts, below = levels_sql(ends, "vmax < qv")
    return f"""SELECT {hit}::DOUBLE AS hit, * FROM ({parts}, v AS (SELECT s.*, p.c0 IS NOT NULL AS seen FROM s LEFT JOIN s p ON p.level = s.level + 1 AND p.c0 = s.c0 // 8 AND p.c1 = s.c1 // 8 AND ((p.meets AND NOT p.whole) OR p.level = (SELECT height FROM h)))
SELECT level, count(*) AS children, count(*) FILTER (whole) AS complete, count(*) FILTER (meets AND NOT whole) AS partial, count(*) FILTER (NOT meets) AS pruned FROM v WHERE seen AND {below} GROUP BY level)"""


def ratio_reduction(hit: float) -> str:
    return repr(reduction(hit, 2))


_HITS = (0.005, 0.1, 0.5, 1.0)


@query("trace_levels", " UNION ALL ".join(map(_trace_sql, _HITS)))
def trace_levels(spark: SparkSession, d: str) -> DataFrame:
    """What the descent meets on each level, by hit ratio."""
    index = index_of(spark, d, "a2p", _EXACT)
    rows = [Q.trace(index, ratio_query(index, h)).withColumn("hit", F.lit(h)) for h in _HITS]
    return reduce(DataFrame.union, rows).select("hit", "level", "children", "complete", "partial", "pruned").where("children > 0")


@query("candidate_counts", " UNION ALL ".join(f"SELECT '{a}' AS array_name, (SELECT count(*) FROM ({ratio_sql(a, 0.1)})) AS hits, true AS within" for a in ("a2", "ae", "a2p")))
def candidate_counts(spark: SparkSession, d: str) -> DataFrame:
    """Cells told by complete nodes, sure cells of leaves and candidates less false positives add up to the hits; a leaf
    reads at most four bitmaps for one range, and its candidates lie in two bins."""
    out = []
    for a in ("a2", "ae", "a2p"):
        index = index_of(spark, d, a)
        q = ratio_query(index, 0.1)
        told = Q.progressive(index, q).where("level >= 0").agg(F.count("*").alias("told"))
        found = Q.leaf_trace(index, q).crossJoin(told)
        hits = F.col("told") + F.col("sure") + F.col("candidates") - F.col("false_positives")
        out.append(found.select(F.lit(a).alias("array_name"), hits.alias("hits"), (F.col("bitmaps") <= 4 * F.col("leaves")).alias("within")))
    return reduce(DataFrame.union, out)


_BLOCK_BITS = " + ".join(f"((x0 >> {j}) & 1) * {1 << (2 * j + 1)} + ((x1 >> {j}) & 1) * {1 << (2 * j)}" for j in range(12))


@query(
    "blocks_read",
    f"""WITH c AS (SELECT *, min(partkey) OVER () AS l0, min(suppkey) OVER () AS l1 FROM ({ARRAYS['a2'].sql})), k AS (SELECT DISTINCT (partkey - l0) // 32 AS c0, (suppkey - l1) // 32 AS c1, l0, l1 FROM c), g AS (SELECT max(partkey) - min(partkey) + 1 AS e0, max(suppkey) - min(suppkey) + 1 AS e1, count(*) AS n FROM c),
lv AS (SELECT min(i) AS lev FROM g, (SELECT unnest(generate_series(0, 6)) AS i) WHERE ceil(ceil(e0 / 32.0) / 8**i) * ceil(ceil(e1 / 32.0) / 8**i) <= greatest(1, least(4096, n // 256))),
x AS (SELECT c0 >> CAST(3 * lev AS INTEGER) AS x0, c1 >> CAST(3 * lev AS INTEGER) AS x1 FROM k, lv WHERE l0 + 32 * c0 < 129 AND l0 + 32 * c0 + 32 > 33 AND l1 + 32 * c1 + 32 > 5)
SELECT DISTINCT {_BLOCK_BITS} AS block, 1 AS reads FROM x""",
)
def blocks_read(spark: SparkSession, d: str) -> DataFrame:
    """Blocks of the cells that a box reads, and how often each: the parts that its chunks lie in, once."""
    return Q.blocks_read(index_of(spark, d, "a2", IndexConfig(part_cells=256)), FIXED["dim_only"][1])


def index_space(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of the three methods' indexes, on arrays of the tables and on generated ones of three sizes."""
    out = []

    def put(name: str, tree: Index, lines: B.LinearIndex, columns: B.LinearIndex) -> None:
        own = Q.index_bytes(tree).agg(F.sum(F.col("bitmap_bytes") + F.col("meta_bytes")).alias("bytes"))
        sizes = [("chunk_tree", own), *((m, B.bitmap_bytes(i).agg(F.sum("bytes").alias("bytes"))) for m, i in (("rect_clip", lines), ("dim_columns", columns)))]
        out.extend(x.select(F.lit(name).alias("array_name"), F.lit(m).alias("method"), "bytes") for m, x in sizes)

    for name in ("a2", "ae"):
        put(name, index_of(spark, d, name, IndexConfig(list_below=0)), linear_of(spark, d, name, encoding="interval", list_below=0), linear_of(spark, d, name, "all", list_below=0))
    for side in (64, 128, 256):
        put(f"gauss_{side}", gauss.index(spark, (side, side), cfg=IndexConfig(list_below=0)), gauss.linear(spark, (side, side), "value", encoding="interval", list_below=0), gauss.linear(spark, (side, side), "all", list_below=0))
    return reduce(DataFrame.union, out)


#: Uncompressed, a space is known from the definition: bits of a block or chunk for each bitmap.
_CHUNKS = ARRAYS["ae"].sql
_RAW = f"""WITH c AS (SELECT *, min("user") OVER () AS l0, min(hour) OVER () AS l1 FROM ({_CHUNKS})), k AS (SELECT *, ("user" - l0) // 16 AS c0, (hour - l1) // 16 AS c1 FROM c),
r AS (SELECT *, row_number() OVER (PARTITION BY c0, c1 ORDER BY value) AS r, count(*) OVER (PARTITION BY c0, c1) AS n FROM k), d AS (SELECT c0, c1, count(DISTINCT value) AS few, max(value) AS top FROM k GROUP BY 1, 2),
e AS (SELECT DISTINCT r.c0, r.c1, value FROM r, (SELECT unnest(generate_series(0, 15)) AS b) WHERE r = b * n // 16 + 1), f AS (SELECT e.c0, e.c1, count(*) AS starts, bool_or(value = top) AS has_top FROM e JOIN d USING (c0, c1) GROUP BY 1, 2),
m AS (SELECT CASE WHEN few <= 16 THEN few ELSE starts - has_top::INT END AS bins FROM f JOIN d USING (c0, c1))
SELECT count(*) AS leaves, sum(bins - 1) AS range_bitmaps, sum((bins + 1) // 2) AS interval_bitmaps, sum(bins) AS equality_bitmaps FROM m"""


@query("bitmap_counts", _RAW)
def bitmap_counts(spark: SparkSession, d: str) -> DataFrame:
    """Bitmaps that each encoding keeps over all leaves, without those of empty cells."""
    out = None
    for enc in ("range", "interval", "equality"):
        leaves = index_of(spark, d, "ae", IndexConfig(leaf_encoding=enc, codec="raw", list_below=0)).leaves
        own = leaves.agg(F.count("*").alias("leaves"), F.sum(F.size("bitmaps")).alias(f"{enc}_bitmaps"))
        out = own if out is None else out.join(own, "leaves")
    return out


add("index_space", lambda s, d: index_space(s, d))


@query("hit_ratios", "SELECT array_name, hit, n_cells, hits FROM (" + " UNION ALL ".join(f"SELECT '{a}' AS array_name, {h}::DOUBLE AS hit, (SELECT count(*) FROM ({ARRAYS[a].sql})) AS n_cells, (SELECT count(*) FROM ({ratio_sql(a, h)})) AS hits" for a in ("a2", "a2p") for h in (0.1, 0.5)) + ")")
def hit_ratios(spark: SparkSession, d: str) -> DataFrame:
    out = []
    for a in ("a2", "a2p"):
        index = index_of(spark, d, a)
        total = index.leaves.agg(F.sum("n_cells").alias("n_cells"))
        out += [total.crossJoin(Q.range_query(index, ratio_query(index, h)).agg(F.count("*").alias("hits"))).select(F.lit(a).alias("array_name"), F.lit(h).alias("hit"), "n_cells", "hits") for h in (0.1, 0.5)]
    return reduce(DataFrame.union, out)


# ---- baselines --------------------------------------------------------------------------------------------------

_B2 = ("a2", ArrayQuery({"partkey": C.between(10, 800), "suppkey": C.between(2, 60)}, C.between(10000.0, 45000.0)), "partkey >= 10 AND partkey < 800 AND suppkey >= 2 AND suppkey < 60 AND value >= 10000.0 AND value < 45000.0")
_W2 = where_sql(_B2[0], _B2[2])
add("baseline_rect_clip", lambda s, d: B.rect_clip(linear_of(s, d, "a2", encoding="interval"), _B2[1]), _W2)
add("baseline_dim_columns", lambda s, d: B.dim_columns(linear_of(s, d, "a2", "all"), _B2[1]), _W2)
for rule in ("equi_width", "v_optimal"):
    add(f"dim_columns_{rule}", lambda s, d, rule=rule: B.dim_columns(linear_of(s, d, "a2", "all", binning=rule), _B2[1]), _W2)
for enc, name in (("bit_sliced", "bit_sliced_range"), ("components", "multi_component_range"), ("two_level", "multi_level_range")):
    add(name, lambda s, d, enc=enc: B.dim_columns(linear_of(s, d, "a2", "all", encoding=enc, bins=64), _B2[1]), _W2)
add("baseline_dim_columns_3d", lambda s, d: B.dim_columns(linear_of(s, d, "a3", "all"), FIXED["mixed_satellite_style"][1]), where_sql("a3", FIXED["mixed_satellite_style"][2]))
add("baseline_rect_clip_3d", lambda s, d: B.rect_clip(linear_of(s, d, "a3", encoding="interval"), FIXED["mixed_satellite_style"][1]), where_sql("a3", FIXED["mixed_satellite_style"][2]))
add("baseline_zone_map", lambda s, d: B.zone_map(index_of(s, d, "a2"), _B2[1]), _W2)
add("baseline_synopsis_tree", lambda s, d: B.synopsis_tree(index_of(s, d, "a2"), _B2[1]), _W2)
add("baseline_grid_filter", lambda s, d: B.grid_filter(index_of(s, d, "a2"), _B2[1]), _W2)
add("baseline_scan", lambda s, d: B.scan(*cells_and_spec(s, d, "a2"), _B2[1]), _W2)
_RUNS = f"""
WITH hits AS ({_W2}), r AS (SELECT *, suppkey - row_number() OVER (PARTITION BY partkey ORDER BY suppkey) AS g FROM hits),
lines AS (SELECT partkey, min(suppkey) AS lo_suppkey, max(suppkey) + 1 AS hi_suppkey FROM r GROUP BY partkey, g),
s AS (SELECT *, partkey - row_number() OVER (PARTITION BY lo_suppkey, hi_suppkey ORDER BY partkey) AS g FROM lines)
SELECT min(partkey) AS lo_partkey, max(partkey) + 1 AS hi_partkey, lo_suppkey, hi_suppkey FROM s GROUP BY lo_suppkey, hi_suppkey, g"""
add("rect_clip_rectangles", lambda s, d: B.clipped_boxes(linear_of(s, d, "a2", encoding="interval"), _B2[1]), _RUNS)
add("rect_clip_sets", lambda s, d: B.rect_clip(linear_of(s, d, "a2", encoding="interval"), FIXED["member_dim"][1]), where_sql("a2", FIXED["member_dim"][2]))
add("rect_clip_1d", lambda s, d: B.rect_clip(linear_of(s, d, "ad", encoding="interval"), ArrayQuery({"doc": C.between(20, 900)}, C.at_least(500.0))), where_sql("ad", "doc >= 20 AND doc < 900 AND value >= 500.0"))


@query("pairwise_agree", f"SELECT count(*) AS hits, 5 AS methods, true AS agree FROM ({_W2})")
def pairwise_agree(spark: SparkSession, d: str) -> DataFrame:
    """All methods give the same cells: each cell is found by all five of them."""
    index = index_of(spark, d, "a2")
    spec = index.spec
    found = [Q.range_query(index, _B2[1]), B.rect_clip(linear_of(spark, d, "a2", encoding="interval"), _B2[1]), B.dim_columns(linear_of(spark, d, "a2", "all"), _B2[1]), B.zone_map(index, _B2[1]), B.synopsis_tree(index, _B2[1])]
    per_cell = reduce(DataFrame.unionByName, found).groupBy(*spec.names, spec.attr).agg(F.count("*").alias("k"))
    return per_cell.agg(F.count("*").alias("hits"), F.lit(5).alias("methods"), (F.min("k") == 5).alias("agree"))


# ---- chunks, orders, bins ---------------------------------------------------------------------------------------

_A2 = ARRAYS["a2"].sql
_PART = "WITH c AS (SELECT *, min(partkey) OVER () AS l0, min(suppkey) OVER () AS l1 FROM ({})), k AS (SELECT *, (partkey - l0) // 32 AS c0, (suppkey - l1) // 32 AS c1, (partkey - l0) % 32 * 32 + (suppkey - l1) % 32 AS cell_no FROM c) ".format(_A2)


@query("chunk_assign", _PART + "SELECT partkey, suppkey, c0, c1, l0 + 32 * c0 AS offset0, least(l0 + 32 * c0 + 32, (SELECT max(partkey) + 1 FROM c)) AS end0, cell_no FROM k")
def chunk_assign(spark: SparkSession, d: str) -> DataFrame:
    cells, spec = cells_and_spec(spark, d, "a2")
    x = linear.with_chunks(cells, spec)
    return x.select("partkey", "suppkey", F.col("chunk_coord")[0].alias("c0"), F.col("chunk_coord")[1].alias("c1"), F.col("offset")[0].alias("offset0"), F.col("end")[0].alias("end0"), "cell_no")


@query("chunk_irregular", f"SELECT CASE WHEN partkey < 50 THEN 0 WHEN partkey < 120 THEN 1 ELSE 2 END AS c0, CASE WHEN suppkey < 4 THEN 0 ELSE 1 END AS c1, count(*) AS n FROM ({_A2}) GROUP BY 1, 2")
def chunk_irregular(spark: SparkSession, d: str) -> DataFrame:
    x = linear.with_irregular_chunks(cells_and_spec(spark, d, "a2")[0], {"partkey": [0, 50, 120], "suppkey": [0, 4]})
    return x.groupBy(F.col("chunk_coord")[0].cast("int").alias("c0"), F.col("chunk_coord")[1].cast("int").alias("c1")).agg(F.count("*").alias("n"))


@query("chunk_synopsis", _PART + "SELECT c0, c1, count(*) AS n_cells, min(value) AS vmin, max(value) AS vmax FROM k GROUP BY 1, 2")
def chunk_synopsis(spark: SparkSession, d: str) -> DataFrame:
    return linear.chunk_synopsis(*cells_and_spec(spark, d, "a2"))


_BITS = " + ".join(f"((c0 >> {j}) & 1) * {1 << (2 * j + 1)} + ((c1 >> {j}) & 1) * {1 << (2 * j)}" for j in range(12))


@query("z_codes", _PART + f"SELECT c0, c1, min({_BITS}) AS z, min(({_BITS}) >> 6) AS parent FROM k GROUP BY 1, 2")
def z_codes(spark: SparkSession, d: str) -> DataFrame:
    syn = linear.chunk_synopsis(*cells_and_spec(spark, d, "a2"))
    z = linear.z_code([F.col("c0"), F.col("c1")], (8, 8), 4)
    return syn.select("c0", "c1", z.alias("z"), linear.z_parent(z, (8, 8)).alias("parent"))


@query("z_decode", _PART + "SELECT DISTINCT c0, c1, c0 AS d0, c1 AS d1 FROM k")
def z_decode(spark: SparkSession, d: str) -> DataFrame:
    syn = linear.chunk_synopsis(*cells_and_spec(spark, d, "a2"))
    d0, d1 = linear.deinterleave(linear.interleave([F.col("c0"), F.col("c1")], 12), 2, 12)
    return syn.select("c0", "c1", d0.alias("d0"), d1.alias("d1"))


add("row_major_codes", lambda s, d: (lambda cells, spec: cells.select(*spec.names, linear.row_major([F.col(n.name) - n.lo for n in spec.dims], [n.extent for n in spec.dims]).alias("at"), linear.row_major([F.col(n.name) - n.lo for n in spec.dims], [n.extent for n in spec.dims], pad=64).alias("padded")))(*cells_and_spec(s, d, "a2")), f"WITH c AS ({_A2}), b AS (SELECT min(partkey) AS l0, min(suppkey) AS l1, max(suppkey) + 1 - min(suppkey) AS w FROM c) SELECT partkey, suppkey, (partkey - l0) * w + suppkey - l1 AS at, (partkey - l0) * ((w + 63) // 64 * 64) + suppkey - l1 AS padded FROM c, b")


def chunked(spark: SparkSession, d: str, name: str = "ae") -> tuple[DataFrame, list[str]]:
    cells, spec = cells_and_spec(spark, d, name)
    return cells.withColumns({f"c{i}": c for i, c in enumerate(linear.chunk_coords(spec))}), [f"c{i}" for i in range(spec.n)]


_AE = 'WITH c AS (SELECT *, min("user") OVER () AS l0, min(hour) OVER () AS l1 FROM ({})), k AS (SELECT *, ("user" - l0) // 16 AS c0, (hour - l1) // 16 AS c1 FROM c)'.format(ARRAYS["ae"].sql)
_RANKED = ", r AS (SELECT *, row_number() OVER (PARTITION BY c0, c1 ORDER BY value) AS r, count(*) OVER (PARTITION BY c0, c1) AS n FROM k), e AS (SELECT DISTINCT c0, c1, value AS lo FROM r, (SELECT unnest(generate_series(0, 15)) AS b) WHERE r = b * n // 16 + 1), g AS (SELECT *, row_number() OVER (PARTITION BY c0, c1 ORDER BY lo) - 1 AS bin_no, lead(lo) OVER (PARTITION BY c0, c1 ORDER BY lo) AS hi FROM e) "
add("leaf_bins_equi_depth", lambda s, d: (lambda df, by: binning.equi_depth_bins(df, "value", 16, by))(*chunked(s, d)), _AE + _RANKED + "SELECT g.c0, g.c1, g.bin_no, g.lo, count(*) AS n FROM g JOIN k ON k.c0 = g.c0 AND k.c1 = g.c1 AND value >= g.lo AND (g.hi IS NULL OR value < g.hi) GROUP BY 1, 2, 3, 4")
add("bins_equi_width", lambda s, d: (lambda df, by: binning.equi_width_bins(df, "value", 8, by))(*chunked(s, d)), _AE + ", m AS (SELECT c0, c1, min(value) AS a, max(value) AS b FROM k GROUP BY 1, 2) SELECT k.c0, k.c1, CAST(coalesce(least(floor((value - a) * 8 / nullif(b - a, 0.0)), 7), 0) AS BIGINT) AS bin_no, count(*) AS n FROM k JOIN m USING (c0, c1) GROUP BY 1, 2, 3")
_WEIGHTED = ", v AS (SELECT c0, c1, value, sum(CASE WHEN value > 50 THEN 5 ELSE 1 END) AS wt FROM k GROUP BY 1, 2, 3), t AS (SELECT *, coalesce(sum(wt) OVER (PARTITION BY c0, c1 ORDER BY value ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before, sum(wt) OVER (PARTITION BY c0, c1) AS total FROM v), e AS (SELECT c0, c1, value AS lo FROM t WHERE before = 0 OR floor((before + wt - 1) * 8 / total) > floor((before - 1) * 8 / total)), g AS (SELECT *, row_number() OVER (PARTITION BY c0, c1 ORDER BY lo) - 1 AS bin_no, lead(lo) OVER (PARTITION BY c0, c1 ORDER BY lo) AS hi FROM e) "
add("bins_weighted", lambda s, d: (lambda df, by: binning.weighted_bins(df, "value", F.when(F.col("value") > 50, 5).otherwise(1), 8, by))(*chunked(s, d)), _AE + _WEIGHTED + "SELECT g.c0, g.c1, g.bin_no, g.lo, count(*) AS n FROM g JOIN k ON k.c0 = g.c0 AND k.c1 = g.c1 AND value >= g.lo AND (g.hi IS NULL OR value < g.hi) GROUP BY 1, 2, 3, 4")
add("bins_singleton", lambda s, d: (lambda df, by: binning.singleton_bins(df, "value", by, 16))(*chunked(s, d, "aet")), 'WITH c AS (SELECT *, min("user") OVER () AS l0, min(hour) OVER () AS l1 FROM ({})), k AS (SELECT *, ("user" - l0) // 16 AS c0, (hour - l1) // 16 AS c1 FROM c), v AS (SELECT c0, c1, value, count(*) AS n FROM k GROUP BY 1, 2, 3) SELECT * FROM v QUALIFY count(*) OVER (PARTITION BY c0, c1) <= 16'.format(ARRAYS["aet"].sql))
add("sketch_edges", lambda s, d: (lambda df, by: binning.sketch_edges(df, "value", 8, by).select(*by, F.posexplode("edges").alias("k", "edge")))(*chunked(s, d)), _AE + ", r AS (SELECT c0, c1, value, row_number() OVER (PARTITION BY c0, c1 ORDER BY value) AS r, count(*) OVER (PARTITION BY c0, c1) AS n FROM k) SELECT c0, c1, j AS k, value AS edge FROM r, (SELECT unnest(generate_series(0, 8)) AS j) WHERE r = greatest(1, CAST(ceil(j * n / 8.0) AS BIGINT))")
add("bitmap_popcounts", lambda s, d: (lambda cells, spec: binning.value_bitmaps(cells, F.col("value"), linear.row_major([F.col(x.name) - x.lo for x in spec.dims], [x.extent for x in spec.dims])).groupBy("key").agg(F.sum(F.bitmap_count("bitmap")).alias("n")))(*cells_and_spec(s, d, "aet")), f"SELECT value AS key, count(*) AS n FROM ({ARRAYS['aet'].sql}) GROUP BY 1")
add("present_counts", lambda s, d: index_of(s, d, "a2").leaves.select(F.col("lo")[0].alias("lo0"), F.col("lo")[1].alias("lo1"), "n_cells", "vmin", "vmax"), _PART + "SELECT l0 + 32 * c0 AS lo0, l1 + 32 * c1 AS lo1, count(*) AS n_cells, min(value) AS vmin, max(value) AS vmax FROM k GROUP BY 1, 2")


# ---- nodes ------------------------------------------------------------------------------------------------------

_FULL = IndexConfig(bins=200, node_values=False)  # more bins than children's bounds, which are the edges: nothing is merged
_KIDS = _PART + ", s AS (SELECT c0, c1, min(value) AS lo, max(value) AS hi FROM k GROUP BY 1, 2), p AS (SELECT c0 // 8 AS p0, c1 // 8 AS p1, c0 % 8 * 8 + c1 % 8 AS slot, lo, hi FROM s), e AS (SELECT DISTINCT p0, p1, unnest([lo, hi]) AS edge FROM p) "


def _parents(spark: SparkSession, d: str) -> DataFrame:
    """Level-1 nodes with their coordinates among parents."""
    index = index_of(spark, d, "a2", _FULL)
    lo = [x.lo for x in index.spec.dims]
    return index.level(1).select(*[((F.col("lo")[i] - lo[i]) / 256).cast("long").alias(f"p{i}") for i in (0, 1)], "*")


add("child_edges", lambda s, d: _parents(s, d).select("p0", "p1", F.explode("edges").alias("edge")), _KIDS + "SELECT p0, p1, edge FROM e")
def _bounds(family: str, threshold: str):
    """p0, p1, edge, slot: the stored bitmaps of a family, as sets."""
    return lambda s, d: _parents(s, d).select("p0", "p1", F.explode(F.arrays_zip(F.col(threshold).alias("edge"), F.col(family).alias("words"))).alias("x")).select("p0", "p1", F.col("x.edge").alias("edge"), F.explode(Q.set_slots("x.words", (8, 8))).alias("slot"))


# a set changes above each beginning and at each end, so just those thresholds are kept
add("double_range_started", _bounds("started", "plus"), _KIDS + ", t AS (SELECT DISTINCT p0, p1, lo AS edge FROM p) SELECT t.p0, t.p1, t.edge, p.slot FROM t JOIN p ON p.p0 = t.p0 AND p.p1 = t.p1 AND p.lo < t.edge")
add("double_range_ended", _bounds("ended", "minus"), _KIDS + ", t AS (SELECT DISTINCT p0, p1, hi AS edge FROM p) SELECT t.p0, t.p1, t.edge, p.slot FROM t JOIN p ON p.p0 = t.p0 AND p.p1 = t.p1 AND p.hi <= t.edge")
add("bin_signs", lambda s, d: _parents(s, d).select("p0", "p1", F.size("plus").cast("long").alias("adding"), F.size("minus").cast("long").alias("ending")), _KIDS + "SELECT p0, p1, count(DISTINCT lo) - 1 AS adding, count(DISTINCT hi) AS ending FROM p GROUP BY 1, 2")
add("nodesin", lambda s, d: (lambda p: p.select("p0", "p1", F.explode(Q.set_slots("inside", (8, 8))).alias("slot")))(_parents(s, d).withColumn("inside", F.array(*[a.bitwiseAND(F.bitwise_not(b)) for a, b in zip(Q.below(F.lit(52000.0), True, 1), Q.over(F.lit(52000.0), False, 1))]))), _KIDS + "SELECT p0, p1, slot FROM p WHERE lo <= 52000.0 AND hi >= 52000.0")


def reduced_nodes(rule: str, spark: SparkSession, d: str) -> DataFrame:
    """Nodes of at most 16 bins held against their children: every stored set is the children's, none is there twice, and
    thresholds are bounds of children."""
    index = index_of(spark, d, "a2", IndexConfig(merge=rule, part_cells=PART_CELLS))
    lo, slots = [x.lo for x in index.spec.dims], F.array(*[F.lit(z) for z in linear.slot_z(index.fanout, index.layout[0])])
    slot = F.array_position(slots, F.col("z").bitwiseAND(F.lit((1 << index.bits(1)) - 1)).cast("int")) - 1
    kids = index.leaves.select(F.shiftright("z", index.bits(1)).alias("z"), F.struct(slot.alias("slot"), "vmin", "vmax").alias("k")).groupBy("z").agg(F.collect_list("k").alias("kids"))
    both = index.level(1).join(kids, "z")
    sets = lambda family, thresholds, test: F.forall(F.arrays_zip(F.col(thresholds).alias("t"), F.col(family).alias("w")), lambda x: F.array_sort(Q.set_slots(x["w"], (8, 8)).cast("array<long>")) == F.array_sort(F.transform(F.filter("kids", lambda k: test(k, x["t"])), lambda k: k["slot"])))
    bounds = F.array_union(F.transform("kids", lambda k: k["vmin"]), F.transform("kids", lambda k: k["vmax"]))
    right = sets("started", "plus", lambda k, t: k["vmin"] < t) & sets("ended", "minus", lambda k, t: k["vmax"] <= t)
    once = (F.size(F.array_distinct("started")) == F.size("started")) & (F.size(F.array_distinct("ended")) == F.size("ended"))
    few = (F.size("edges") <= 17) & F.forall("edges", lambda e: F.array_contains(bounds, e))
    return both.select(*[((F.col("lo")[i] - lo[i]) / 256).cast("long").alias(f"p{i}") for i in (0, 1)], F.size("kids").cast("long").alias("children"), "vmin", "vmax", right.alias("right_sets"), once.alias("no_set_twice"), few.alias("at_most_16_bins"))


for rule in ("equi_depth", "equi_width", "by_sign"):
    add(f"reduced_nodes_{rule}", partial(reduced_nodes, rule), _KIDS + "SELECT p0, p1, count(*) AS children, min(lo) AS vmin, max(hi) AS vmax, true AS right_sets, true AS no_set_twice, true AS at_most_16_bins FROM p GROUP BY 1, 2")


@query("dim_masks", "SELECT d, bucket, kind, slot FROM (SELECT unnest([0, 1]) AS d), (SELECT unnest(generate_series(0, 7)) AS bucket), (SELECT unnest(['at', 'from', 'upto']) AS kind), (SELECT unnest(generate_series(0, 63)) AS slot) WHERE CASE kind WHEN 'at' THEN (CASE d WHEN 0 THEN slot // 8 ELSE slot % 8 END) = bucket WHEN 'from' THEN (CASE d WHEN 0 THEN slot // 8 ELSE slot % 8 END) >= bucket ELSE (CASE d WHEN 0 THEN slot // 8 ELSE slot % 8 END) <= bucket END")
def dim_masks(spark: SparkSession, d: str) -> DataFrame:
    m = Q.dim_masks((8, 8))
    rows = [(dim, b, kind, words) for kind, t in (("at", m.at), ("from", m.from_), ("upto", m.upto)) for dim, r in enumerate(t) for b, words in enumerate(r)]
    return spark.createDataFrame(rows, "d int, bucket long, kind string, words array<long>").select("d", "bucket", "kind", F.explode(Q.set_slots("words", (8, 8))).alias("slot"))


@query("wsse_compare", _KIDS + ", m AS (SELECT c0 // 8 AS p0, c1 // 8 AS p1, count(*) AS n_cells FROM k GROUP BY 1, 2) SELECT e.p0, e.p1, count(*) AS n_edges, min(n_cells) AS n_cells, true AS ordered FROM e JOIN m USING (p0, p1) GROUP BY 1, 2")
def wsse_compare(spark: SparkSession, d: str) -> DataFrame:
    """Edges of each parent reduced to 8 bins in three ways: mass is kept, the exchange ends no worse than it began, and
    no better than the optimum."""
    rows = _parents(spark, d).select("p0", "p1", "edges", "weights")

    def run(batches):
        import numpy as np
        import pandas as pd

        for pdf in batches:
            out = []
            for r in pdf.itertuples():
                e, w = np.array(r.edges), np.array(r.weights)
                error = {k: E.wsse(E.merged_mass(e, w, E.REDUCE[k](e, w, 8)), 8) for k in ("equi_width", "equi_depth", "optimal")}
                begin = E.wsse(E.merged_mass(e, w, E.begin_equi_depth(e, w, 8)), 8)
                slack = 1e-9 * (1 + begin)
                ordered = error["optimal"] <= error["equi_depth"] + slack and error["equi_depth"] <= begin + slack
                out.append((r.p0, r.p1, len(e), round(float(w.sum())), ordered))
            yield pd.DataFrame(out, columns=["p0", "p1", "n_edges", "n_cells", "ordered"])

    return rows.mapInPandas(run, "p0 long, p1 long, n_edges long, n_cells long, ordered boolean")


# ---- append, modification, layout -------------------------------------------------------------------------------

_LATER = ("ae", ArrayQuery({"user": C.below(100)}, C.between(10.0, 90.0)), '"user" < 100 AND value >= 10.0 AND value < 90.0')


def appended(spark: SparkSession, d: str, rebalance: bool) -> DataFrame:
    """The first hours are indexed, the rest is appended in three slices along the hour dimension. Users are known from
    the start; hours grow."""
    cells, spec = cells_and_spec(spark, d, "ae")
    cells = written(cells, "cells")
    cuts = [spec.dims[1].lo + spec.dims[1].extent * k // 5 for k in (2, 3, 4)]
    first = cells.where(F.col("hour") < cuts[0])
    known = fit_spec(first, spec.names, spec.chunk, domain={"user": (spec.dims[0].lo, spec.dims[0].hi), "hour": (spec.dims[1].lo, cuts[0])})
    index: Index = build_index(first, known, IndexConfig(fanout=(4, 4), part_cells=1 << 12))
    for a, b in zip(cuts, [*cuts[1:], spec.dims[1].hi]):
        index = A.append(index, cells.where((F.col("hour") >= a) & (F.col("hour") < b)), rebalance)
    return Q.range_query(read_index(spark, index.path), _LATER[1])


add("append_equals_rebuild", lambda s, d: appended(s, d, False), where_sql(_LATER[0], _LATER[2]))
add("append_rebalanced", lambda s, d: appended(s, d, True), where_sql(_LATER[0], _LATER[2]))


@query("append_below_origin", where_sql(_LATER[0], _LATER[2]))
def append_below_origin(spark: SparkSession, d: str) -> DataFrame:
    """Later hours first: what is appended lies below the origin, so the index is built anew as its next version."""
    cells, spec = cells_and_spec(spark, d, "ae")
    middle = spec.dims[1].lo + spec.dims[1].extent // 2
    late = cells.where(F.col("hour") >= middle)
    index = build_index(late, fit_spec(late, spec.names, spec.chunk), IndexConfig(part_cells=PART_CELLS))
    return Q.range_query(A.append(index, cells.where(F.col("hour") < middle)), _LATER[1])


@query("modify_cells", f"SELECT partkey, suppkey, value FROM (SELECT partkey, suppkey, CASE WHEN value >= 30000.0 THEN value - 20000.0 ELSE value END AS value FROM ({_A2})) WHERE value >= 20000.0 AND value < 50000.0")
def modify_cells(spark: SparkSession, d: str) -> DataFrame:
    """All cells of 30,000 or more lose 20,000."""
    index = build_index(*cells_and_spec(spark, d, "a2"), IndexConfig(part_cells=PART_CELLS))
    changed = index.cells.where("value >= 30000.0").select("partkey", "suppkey", (F.col("value") - 20000.0).alias("value"))
    return Q.range_query(A.modify(index, changed), ArrayQuery({}, C.between(20000.0, 50000.0)))


@query("compress_runs", f"WITH c AS ({_A2}), b AS (SELECT min(partkey) AS l0, min(suppkey) AS l1, max(suppkey) + 1 - min(suppkey) AS w FROM c), p AS (SELECT (partkey - l0) * w + suppkey - l1 AS pos FROM c, b WHERE suppkey = l1 + 1) SELECT count(DISTINCT pos - r) AS runs FROM (SELECT pos, row_number() OVER (ORDER BY pos) AS r FROM p)")
def compress_runs(spark: SparkSession, d: str) -> DataFrame:
    """Runs of ones of one column in row-major order: as many as rows, which no run-length code shortens."""
    cells, spec = cells_and_spec(spark, d, "a2")
    at = linear.row_major([F.col(x.name) - x.lo for x in spec.dims], [x.extent for x in spec.dims])
    ones = cells.where(F.col("suppkey") == spec.dims[1].lo + 1).select(at.alias("at"))
    # a run begins where the place before is no one: an anti join needs no global order
    starts = ones.alias("a").join(ones.select((F.col("at") + 1).alias("next")), F.col("a.at") == F.col("next"), "left_anti")
    return starts.agg(F.count("*").alias("runs"))


# ---- generated arrays -------------------------------------------------------------------------------------------

add("sum_gauss_grid", lambda s, d: gauss.sum_gauss(s, (16, 16), gauss.FIXED_2D).select("d0", "d1", F.round("value", 9).alias("value")), gauss.sql((16, 16), gauss.FIXED_2D))
add("sum_gauss_sparse", lambda s, d: gauss.sum_gauss(s, (16, 16), gauss.FIXED_2D, threshold=0.002).select("d0", "d1", F.round("value", 9).alias("value")), f"SELECT * FROM ({gauss.sql((16, 16), gauss.FIXED_2D)}) WHERE value >= 0.002")
add("sum_gauss_range", lambda s, d: Q.range_query(gauss.index(s, (64, 64)), ArrayQuery({"d0": C.between(5, 50)}, C.between(0.0005, 0.003))).select("d0", "d1"), f"SELECT d0, d1 FROM ({gauss.sql((64, 64), gauss.FIXED_2D, digits=15)}) WHERE d0 >= 5 AND d0 < 50 AND value >= 0.0005 AND value < 0.003")


# ---- operators around the arrays --------------------------------------------------------------------------------

add("topk_in_box", lambda s, d: Q.range_query(index_of(s, d, "a2"), ArrayQuery({"partkey": C.below(500)})).orderBy(F.desc("value"), "partkey", "suppkey").limit(20), where_sql("a2", "partkey < 500") + " ORDER BY value DESC, partkey, suppkey LIMIT 20")
add("slice_dim", lambda s, d: Q.range_query(index_of(s, d, "a3"), ArrayQuery({"month": C.eq(12)})).drop("month"), f"SELECT partkey, suppkey, value FROM ({ARRAYS['a3'].sql}) WHERE month = 12")
add("reduce_along_dim", lambda s, d: index_of(s, d, "a3").cells.groupBy("month").agg(F.max("value").alias("vmax"), F.count("*").alias("n")), f"SELECT month, max(value) AS vmax, count(*) AS n FROM ({ARRAYS['a3'].sql}) GROUP BY 1")
add("rollup_dims", lambda s, d: load(s, d, "supplier").join(F.broadcast(load(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(load(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.max("s_acctbal").alias("best")), "SELECT r_name, n_name, count(*) AS n, max(s_acctbal) AS best FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
add("cube_dims", lambda s, d: load(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.max("l_quantity").alias("most")), "SELECT l_returnflag, l_linestatus, count(*) AS n, max(l_quantity) AS most FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
add("neighbourhood_window", lambda s, d: cells_and_spec(s, d, "ae")[0].withColumn("peak", F.max("value").over(Window.partitionBy("user").orderBy("hour").rangeBetween(-3, 3))), f'SELECT "user", hour, value, max(value) OVER (PARTITION BY "user" ORDER BY hour RANGE BETWEEN 3 PRECEDING AND 3 FOLLOWING) AS peak FROM ({ARRAYS["ae"].sql})')
add("array_join", lambda s, d: cells_and_spec(s, d, "a2")[0].join(cells_and_spec(s, d, "a2p")[0].withColumnRenamed("value", "retail"), ["partkey", "suppkey"]), f"SELECT partkey, suppkey, a.value, b.value AS retail FROM ({_A2}) a JOIN ({ARRAYS['a2p'].sql}) b USING (partkey, suppkey)")
add("fill_empty_cells", lambda s, d: load(s, d, "documents").select(F.col("doc_id").alias("doc")).join(cells_and_spec(s, d, "al")[0], "doc", "left"), f"SELECT doc_id AS doc, value FROM documents LEFT JOIN ({ARRAYS['al'].sql}) ON doc = doc_id")
add("anti_empty_cells", lambda s, d: load(s, d, "documents").select(F.col("doc_id").alias("doc")).join(cells_and_spec(s, d, "al")[0], "doc", "left_anti"), "SELECT doc_id AS doc FROM documents WHERE NOT EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = documents.doc_id AND quality IS NOT NULL)")
add("json_attr", lambda s, d: load(s, d, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n")), "SELECT json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY 1")
add("tumbling_cells", lambda s, d: load(s, d, "events").groupBy(F.window("ts", "1 hour").alias("w"), "user_id").agg(F.max("value").alias("vmax")).select(F.date_format("w.start", "yyyy-MM-dd HH").alias("hour"), "user_id", "vmax"), "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS hour, user_id, max(value) AS vmax FROM events GROUP BY 1, 2")
add("chunk_topk", lambda s, d: (lambda df, by: df.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("value"), "user", "hour"))).where("r <= 2").select(*by, "user", "hour", "r"))(*chunked(s, d)), _AE + ' SELECT c0, c1, "user", hour, r FROM (SELECT *, row_number() OVER (PARTITION BY c0, c1 ORDER BY value DESC, "user", hour) AS r FROM k) WHERE r <= 2')


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)


__all__ = ["choose_fanout", "complete_query", "oracle_sql", "queries"]
