"""Arrays over the given tables, their indexes (built once for a session and folder), and queries of a given hit ratio."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import ArrayQuery, ArraySpec, Constraint, as_array, collapsed, fit_spec
from ..operators.baselines import LinearIndex, build_linear
from ..operators.tree import Index, IndexConfig, build_index


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def month(c: str) -> F.Column:
    """Months since January 1995."""
    return (F.year(c) - 1995) * 12 + F.month(c) - 1


def hour(c: str) -> F.Column:
    """Hours since 2024-01-01."""
    return F.datediff(F.col(c).cast("date"), F.lit("2024-01-01").cast("date")) * 24 + F.hour(c)


#: Entries of a dictionary that may be sorted in one task and broadcast.
MOST_ENTRIES = 100_000


def with_ordinal(df: DataFrame, col: str) -> DataFrame:
    """df with <col>_no: the ordinal of the column's value among its distinct values, from 0. For dictionaries: more than
    MOST_ENTRIES values raise. Rows without a value go."""
    values = sorted(r[0] for r in df.where(F.col(col).isNotNull()).select(col).distinct().limit(MOST_ENTRIES + 1).collect())
    if len(values) > MOST_ENTRIES:
        raise ValueError(f"{col} has more than {MOST_ENTRIES} values: not a dictionary")
    entries = df.sparkSession.createDataFrame([(v, i) for i, v in enumerate(values)], f"{col} string, {col}_no long")
    return df.join(F.broadcast(entries), col)


@dataclass(frozen=True)
class ArrayDef:
    """rows are the array's cells before those at one coordinate collapse; dims, chunk and sql (a DuckDB subquery of the
    collapsed cells) describe it."""

    rows: Callable[[SparkSession, str], DataFrame]
    dims: tuple[str, ...]
    chunk: tuple[int, ...]
    sql: str
    fanout: tuple[int, ...] | None = None

    def cells(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return collapsed(self.rows(spark, sf_dir), self.dims)


_rows = partial(as_array, on_collision="none")

ARRAYS: dict[str, ArrayDef] = {
    "a2": ArrayDef(lambda s, d: _rows(load(s, d, "lineitem"), {"partkey": F.col("l_partkey"), "suppkey": F.col("l_suppkey")}, F.col("l_extendedprice")), ("partkey", "suppkey"), (32, 32), "SELECT l_partkey AS partkey, l_suppkey AS suppkey, max(l_extendedprice) AS value FROM lineitem GROUP BY 1, 2"),
    "a2q": ArrayDef(lambda s, d: _rows(load(s, d, "lineitem"), {"partkey": F.col("l_partkey"), "suppkey": F.col("l_suppkey")}, F.col("l_quantity")), ("partkey", "suppkey"), (32, 32), "SELECT l_partkey AS partkey, l_suppkey AS suppkey, max(l_quantity) AS value FROM lineitem GROUP BY 1, 2"),
    "a2p": ArrayDef(lambda s, d: _rows(load(s, d, "lineitem").join(load(s, d, "part"), F.col("l_partkey") == F.col("p_partkey")), {"partkey": F.col("l_partkey"), "suppkey": F.col("l_suppkey")}, F.col("p_retailprice")), ("partkey", "suppkey"), (32, 32), "SELECT l_partkey AS partkey, l_suppkey AS suppkey, max(p_retailprice) AS value FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"),
    "a3": ArrayDef(lambda s, d: _rows(load(s, d, "lineitem"), {"partkey": F.col("l_partkey"), "suppkey": F.col("l_suppkey"), "month": month("l_shipdate")}, F.col("l_extendedprice")), ("partkey", "suppkey", "month"), (64, 16, 8), "SELECT l_partkey AS partkey, l_suppkey AS suppkey, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS month, max(l_extendedprice) AS value FROM lineitem GROUP BY 1, 2, 3"),
    "a4": ArrayDef(lambda s, d: _rows(load(s, d, "lineitem"), {"partkey": F.col("l_partkey"), "suppkey": F.col("l_suppkey"), "month": month("l_shipdate"), "line": F.col("l_linenumber") - 1}, F.col("l_extendedprice")), ("partkey", "suppkey", "month", "line"), (64, 16, 8, 2), "SELECT l_partkey AS partkey, l_suppkey AS suppkey, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS month, l_linenumber - 1 AS line, max(l_extendedprice) AS value FROM lineitem GROUP BY 1, 2, 3, 4"),
    "a5": ArrayDef(lambda s, d: _rows(load(s, d, "lineitem"), {"partkey": F.col("l_partkey"), "suppkey": F.col("l_suppkey"), "month": month("l_shipdate"), "line": F.col("l_linenumber") - 1, "quantity": F.col("l_quantity").cast("long") - 1}, F.col("l_extendedprice")), ("partkey", "suppkey", "month", "line", "quantity"), (64, 32, 16, 4, 16), "SELECT l_partkey AS partkey, l_suppkey AS suppkey, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS month, l_linenumber - 1 AS line, CAST(l_quantity AS BIGINT) - 1 AS quantity, max(l_extendedprice) AS value FROM lineitem GROUP BY 1, 2, 3, 4, 5"),
    "ae": ArrayDef(lambda s, d: _rows(load(s, d, "events"), {"user": F.col("user_id"), "hour": hour("ts")}, F.col("value")), ("user", "hour"), (16, 16), "SELECT user_id AS \"user\", date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) * 24 + hour(ts) AS hour, max(value) AS value FROM events WHERE value IS NOT NULL AND NOT isnan(value) GROUP BY 1, 2"),
    "av": ArrayDef(lambda s, d: _rows(load(s, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("component", "x")), {"vec": F.col("vec_id"), "component": F.col("component")}, F.col("x")), ("vec", "component"), (16, 16), "SELECT vec_id AS vec, component, max(CAST(x AS DOUBLE)) AS value FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) - 1 AS component FROM embeddings) GROUP BY 1, 2"),
    "ao": ArrayDef(lambda s, d: _rows(load(s, d, "orders"), {"cust": F.col("o_custkey"), "day": F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date"))}, F.col("o_totalprice")), ("cust", "day"), (64, 64), "SELECT o_custkey AS cust, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS day, max(o_totalprice) AS value FROM orders GROUP BY 1, 2"),
    "ac": ArrayDef(lambda s, d: _rows(load(s, d, "conversations"), {"conv": F.col("conv_id"), "turn": F.col("turn")}, F.length("text")), ("conv", "turn"), (16, 8), "SELECT conv_id AS conv, turn, CAST(max(length(text)) AS DOUBLE) AS value FROM conversations WHERE text IS NOT NULL GROUP BY 1, 2"),
    "ad": ArrayDef(lambda s, d: _rows(load(s, d, "documents"), {"doc": F.col("doc_id")}, F.col("n_chars")), ("doc",), (64,), "SELECT doc_id AS doc, CAST(max(n_chars) AS DOUBLE) AS value FROM documents GROUP BY 1"),
    "al": ArrayDef(lambda s, d: _rows(load(s, d, "labels"), {"doc": F.col("doc_id")}, F.col("quality")), ("doc",), (64,), "SELECT doc_id AS doc, CAST(max(quality) AS DOUBLE) AS value FROM labels WHERE quality IS NOT NULL GROUP BY 1"),
    "ak": ArrayDef(lambda s, d: _rows(load(s, d, "customer"), {"nation": F.col("c_nationkey"), "cust": F.col("c_custkey")}, F.col("c_acctbal")), ("nation", "cust"), (8, 32), "SELECT c_nationkey AS nation, c_custkey AS cust, max(c_acctbal) AS value FROM customer GROUP BY 1, 2"),
    "an": ArrayDef(lambda s, d: _rows(load(s, d, "nation"), {"region": F.col("n_regionkey"), "nation": F.col("n_nationkey")}, F.lit(1)), ("region", "nation"), (8, 8), "SELECT n_regionkey AS region, n_nationkey AS nation, 1.0::DOUBLE AS value FROM nation"),
    "ag": ArrayDef(lambda s, d: _rows(load(s, d, "pages"), {"page": F.col("page_id")}, F.length("html")), ("page",), (64,), "SELECT page_id AS page, CAST(max(length(html)) AS DOUBLE) AS value FROM pages WHERE html IS NOT NULL GROUP BY 1"),
    "aet": ArrayDef(lambda s, d: _rows(with_ordinal(load(s, d, "events"), "event_type"), {"user": F.col("user_id"), "hour": hour("ts")}, F.col("event_type_no")), ("user", "hour"), (16, 16), "SELECT user_id AS \"user\", date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) * 24 + hour(ts) AS hour, CAST(max(no) AS DOUBLE) AS value FROM (SELECT *, dense_rank() OVER (ORDER BY event_type) - 1 AS no FROM events) GROUP BY 1, 2"),
    "ap": ArrayDef(lambda s, d: _rows(with_ordinal(load(s, d, "part"), "p_brand"), {"brand": F.col("p_brand_no"), "size": F.col("p_size") - 1}, F.col("p_retailprice")), ("brand", "size"), (8, 8), "SELECT dense_rank() OVER (ORDER BY p_brand) - 1 AS brand, p_size - 1 AS size, p_retailprice AS value FROM part"),
}
ARRAYS["ap"] = ArrayDef(ARRAYS["ap"].rows, ARRAYS["ap"].dims, ARRAYS["ap"].chunk, f"SELECT brand, size, max(value) AS value FROM ({ARRAYS['ap'].sql}) GROUP BY 1, 2")

_BUILT: dict[tuple, Index] = {}
_LINEAR: dict[tuple, LinearIndex] = {}
_CELLS: dict[tuple, tuple[DataFrame, ArraySpec]] = {}


def cells_and_spec(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, ArraySpec]:
    a = ARRAYS[name]
    cells = a.cells(spark, sf_dir)
    return cells, fit_spec(cells, a.dims, a.chunk)


def _cells_to_deal(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, ArraySpec, bool]:
    """Cells and spec for an index: the stored cells, or if there are none yet the rows that collapse to them (True)."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key in _CELLS:
        return *_CELLS[key], False
    a = ARRAYS[name]
    rows = a.rows(spark, sf_dir)
    return rows, fit_spec(rows, a.dims, a.chunk), True


def _known(key: tuple, index: Index | LinearIndex) -> Index | LinearIndex:
    """The index; its cells are the array's stored ones from now on, if there were none."""
    if key not in _CELLS:
        _CELLS[key] = index.cells.select(*index.spec.names, index.spec.attr), replace(index.spec, chunk=ARRAYS[key[2]].chunk)
    return index


#: The given tables are small: parts of so few cells that queries have something to leave out.
PART_CELLS = 1 << 15


def index_of(spark: SparkSession, sf_dir: str, name: str, cfg: IndexConfig | None = None, chunk: tuple[int, ...] | None = None) -> Index:
    """The array's index; built at its first use in this application, kept in the shared folder. Where the collapsed cells
    are not stored yet, they collapse as they are dealt for the index, whose cells then are the stored ones."""
    cfg = cfg or IndexConfig(part_cells=PART_CELLS)
    key = (spark.sparkContext.applicationId, sf_dir, name, cfg, chunk)
    if key not in _BUILT:
        cells, spec, raw = _cells_to_deal(spark, sf_dir, name)
        _BUILT[key] = _known(key[:3], build_index(cells, replace(spec, chunk=chunk or spec.chunk), cfg, raw=raw))
    return _BUILT[key]


def linear_of(spark: SparkSession, sf_dir: str, name: str, columns: str = "value", **options) -> LinearIndex:
    """A stored index of the baselines: of the attribute ("value") or of all dimensions as well ("all")."""
    key = (spark.sparkContext.applicationId, sf_dir, name, columns, tuple(sorted(options.items())))
    if key not in _LINEAR:
        cells, spec, raw = _cells_to_deal(spark, sf_dir, name)
        _LINEAR[key] = _known(key[:3], build_linear(cells, spec, [*spec.names, spec.attr] if columns == "all" else [spec.attr], raw=raw, **options))
    return _LINEAR[key]


def value_bounds(index: Index) -> tuple[float, float]:
    row = index.level(index.height).select("vmin", "vmax").first()
    return row["vmin"], row["vmax"]


def reduction(hit: float, n: int) -> float:
    """The same reduction for each of n dimensions and the attribute that leaves `hit` of all cells."""
    return hit ** (1 / (n + 1))


def ratio_query(index: Index, hit: float) -> ArrayQuery:
    """The first part of every dimension's domain and of the value range; closed at the top for hit = 1."""
    r = reduction(hit, index.spec.n)
    lo, hi = value_bounds(index)
    dims = {d.name: Constraint.between(d.lo, d.lo + int(-(-(r * d.extent) // 1))) for d in index.spec.dims}
    return ArrayQuery(dims, Constraint.at_most(hi) if hit >= 1 else Constraint.below(lo + r * (hi - lo)))


def ratio_sql(name: str, hit: float) -> str:
    """The same query over the plain cells, for DuckDB."""
    a = ARRAYS[name]
    r = repr(reduction(hit, len(a.dims)))
    q = lambda d: f'"{d}"'
    bounds = ", ".join(f"min({q(d)}) AS l{i}, max({q(d)}) + 1 AS h{i}" for i, d in enumerate(a.dims))
    inside = " AND ".join(f"{q(d)} < l{i} + CAST(ceil({r}::DOUBLE * (h{i} - l{i})) AS BIGINT)" for i, d in enumerate(a.dims))
    value = "value <= vh" if hit >= 1 else f"value < vl + {r}::DOUBLE * (vh - vl)"
    return f"WITH cells AS ({a.sql}), b AS (SELECT {bounds}, min(value) AS vl, max(value) AS vh FROM cells) SELECT {', '.join(map(q, a.dims))}, value FROM cells, b WHERE {inside} AND {value}"


def where_sql(name: str, condition: str) -> str:
    a = ARRAYS[name]
    return f"SELECT {', '.join(chr(34) + d + chr(34) for d in a.dims)}, value FROM ({a.sql}) WHERE {condition}"
